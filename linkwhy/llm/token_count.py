"""Operator 1: token counts by heap-and-linked-list byte-pair merging."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bpe import SLICE, count_by_heap, default_vocabulary, merge_table, slices

#: Distinct pre-tokens whose counts a worker keeps; beyond it the store is emptied.
KEPT_WORDS = 1 << 20


class _Counts(dict):
    """Token counts by pre-token, made on first use and bounded."""

    def __init__(self, table):
        super().__init__()
        self.table = table

    def __missing__(self, word: str) -> int:
        n = count_by_heap(self.table, word.encode("utf-8", "surrogatepass"))
        if len(self) >= KEPT_WORDS:
            self.clear()
        if len(word) <= 64:
            self[word] = n
        return n


_KNOWN: dict[str, _Counts] = {}


def counter(path: str):
    """A function from a text to its number of tokens; one store per worker process."""
    if path not in _KNOWN:
        _KNOWN[path] = _Counts(merge_table(path))
    counts = _KNOWN[path]
    table = counts.table

    def count(text: str) -> int:
        n = 0
        for special, part in table.pieces(text):
            if special is not None:
                n += 1
                continue
            for piece in slices(part):
                if len(piece) <= 2 * SLICE:
                    n += sum(map(counts.__getitem__, table.pattern.findall(piece)))
                else:  # no place to cut it: pre-tokens one by one
                    n += sum(counts[m[0]] for m in table.pattern.finditer(piece))
        return n

    return count


def count_tokens(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", vocabulary: str | None = None, limit: int = 1024) -> DataFrame:
    """Bytes and tokens of every whole text: id, n_bytes, n_tokens, over_limit.

    Null and empty texts have 0 of both.  Repeated rows each give a row; a null id stays
    null; other columns are not read.  Texts are cut for memory only where pre-tokens end,
    so a text of any length gives the count of the whole.  An empty table gives no rows.
    There is no shuffle: one pass over the scan.
    """
    path = vocabulary or default_vocabulary()

    def run(batches):
        import pyarrow as pa

        count = counter(path)
        for batch in batches:
            texts = batch.column(1)
            tokens = [0 if t is None else count(t) for t in (x.as_py() for x in texts)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(tokens, pa.int64())], names=["id", "n_tokens"])

    base = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    kind = base.schema["id"].dataType.simpleString()

    def with_bytes(batches):
        import pyarrow as pa
        import pyarrow.compute as pc

        for batch in batches:
            size = pc.fill_null(pc.binary_length(batch.column(1)), 0).cast(pa.int64())
            for out in run([batch]):
                yield pa.RecordBatch.from_arrays([out.column(0), size, out.column(1)], names=["id", "n_bytes", "n_tokens"])

    counted = base.mapInArrow(with_bytes, f"id {kind}, n_bytes long, n_tokens long")
    return counted.select(F.col("id").alias(id_col), "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))
