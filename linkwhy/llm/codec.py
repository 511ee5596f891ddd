"""Operator 8: byte-pair encoding by a bounded-lookahead transducer, and decoding."""

from __future__ import annotations

import hashlib
import struct

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bpe import SLICE, TextDecoder, Transducer, default_vocabulary, merge_table, slices
from .common import blocks, tidy

#: Pre-tokens whose identifiers a worker remembers; about 100 MB.
KEPT_WORDS = 1 << 19


class _Encoded(dict):
    """Identifiers by pre-token as little-endian 32-bit integers, made on first use and bounded."""

    def __init__(self, table):
        super().__init__()
        self.table = table
        self.transducer = Transducer(table)

    def __missing__(self, word: str) -> bytes:
        ids = _packed(self.transducer.encode(word.encode("utf-8", "surrogatepass")))
        if len(self) >= KEPT_WORDS:
            self.clear()
        if len(word) <= 64:
            self[word] = ids
        return ids


_KNOWN: dict[str, _Encoded] = {}


def encoder(path: str):
    """A function from a text to pieces of its identifiers (bytes of little-endian 32-bit integers)."""
    if path not in _KNOWN:
        _KNOWN[path] = _Encoded(merge_table(path))
    store = _KNOWN[path]
    table = store.table

    def encode(text: str):
        for special, part in table.pieces(text):
            if special is not None:
                yield special.to_bytes(4, "little")
                continue
            for piece in slices(part):
                if len(piece) <= 2 * SLICE:
                    yield b"".join(map(store.__getitem__, table.pattern.findall(piece)))
                else:
                    yield from _streamed(store, piece)

    return encode


def _streamed(store: _Encoded, piece: str):
    """Identifiers of a text without places to cut it: pre-tokens one by one, long ones in parts."""
    held = []
    for m in store.table.pattern.finditer(piece):
        a, b = m.span()
        if b - a <= SLICE:
            held.append(store[m[0]])
            if len(held) < 1 << 12:
                continue
        yield b"".join(held)
        held = []
        if b - a > SLICE:
            for at in range(a, b, SLICE):
                yield _packed(store.transducer.feed(piece[at : min(b, at + SLICE)].encode("utf-8", "surrogatepass")))
            yield _packed(store.transducer.finish())
    yield b"".join(held)


def _packed(ids: list[int]) -> bytes:
    return struct.pack(f"<{len(ids)}I", *ids)


def encode_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", vocabulary: str | None = None, digests: bool = False, keep: tuple[str, ...] = (), verify: bool = False) -> DataFrame:
    """Encode every whole text and decode it again.

    Returns id, the columns in ``keep``, ids (array of int), decoded (string) and n_tokens; with
    ``verify`` round_trip (whether the decoded text is the text) in place of the decoded
    text; with ``digests`` instead id, n_tokens, ids_sha256 and decoded_sha256, made piece by
    piece so that a long text needs no more memory than one piece.  Null and empty texts have no
    identifiers and decode to the empty text.  Repeated rows each give a row; an empty
    table gives none.  There is no shuffle.
    """
    path = vocabulary or default_vocabulary()
    names = ["n_tokens", "ids_sha256", "decoded_sha256"] if digests else ["ids", "round_trip" if verify else "decoded", "n_tokens"]
    keep = tuple(k for k in keep if k not in (id_col, *names))  # an output's name goes to the output
    base = docs.select(F.col(id_col).alias("__id"), F.col(text_col).alias("__text"), *keep)
    kinds = {f.name: f.dataType.simpleString() for f in base.schema.fields}

    def run(batches):
        import numpy as np
        import pyarrow as pa

        encode, table = encoder(path), merge_table(path)
        for batch in blocks(batches, 1):
            columns = [[], [], []]
            for t in batch.column(1):
                text = t.as_py() or ""
                decoder = TextDecoder(table)
                sha_ids, sha_text, n, all_ids, all_text, same, at = hashlib.sha256(), hashlib.sha256(), 0, [], [], True, 0
                for piece in encode(text):
                    got = decoder.feed(np.frombuffer(piece, "<u4").tolist())
                    n += len(piece) // 4
                    if digests:
                        sha_ids.update(piece)
                        sha_text.update(got.encode("utf-8", "surrogatepass"))
                    else:
                        all_ids.append(piece)
                        if verify:
                            same, at = same and text.startswith(got, at), at + len(got)
                        else:
                            all_text.append(got)
                tail = decoder.finish()
                if digests:
                    sha_text.update(tail.encode())
                    row = (n, sha_ids.hexdigest(), sha_text.hexdigest())
                else:
                    back = same and text[at:] == tail if verify else "".join(all_text) + tail
                    row = (np.frombuffer(b"".join(all_ids), "<i4"), back, n)
                for column, value in zip(columns, row, strict=True):
                    column.append(value)
            kinds_out = [pa.int64(), pa.string(), pa.string()] if digests else [pa.list_(pa.int32()), pa.bool_() if verify else pa.string(), pa.int64()]
            kept = [batch.column(i) for i in range(batch.num_columns) if i != 1]
            yield pa.RecordBatch.from_arrays([*kept, *(pa.array(c, k) for c, k in zip(columns, kinds_out, strict=True))], names=["__id", *keep, *names])

    types = ["long", "string", "string"] if digests else ["array<int>", "boolean" if verify else "string", "long"]
    schema = ", ".join(f"`{n}` {k}" for n, k in [("__id", kinds["__id"]), *((k, kinds[k]) for k in keep), *zip(names, types, strict=True)])
    out = base.mapInArrow(tidy(run), schema)
    return out.select(F.col("__id").alias(id_col), *keep, *names)
