"""Operator 9: benchmark decontamination by n-gram seeds and Smith-Waterman alignment."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import blocks, joined, tidy, word_hashes, word_spans


@dataclass(frozen=True)
class Rules:
    """n: words of a seed.  Every n-gram of an item is a seed, however many documents hold it:
    in a passage copied often the n-grams that its edits left whole are the common ones.
    least_seeds: different seeds of an item near one diagonal that lead to an alignment.  Scores: a matching word 1, a differing or
    missing word ``penalty``.  least_score: score by words of the item from which a passage is
    contamination.  least_words: an item with fewer words must stand whole, word by word, in a document."""

    n: int = 3
    least_seeds: int = 2
    penalty: float = 0.5
    least_score: float = 0.5
    least_words: int = 8
    block_words: int = 2_000_000


#: Bytes between words: all ASCII but letters and digits.
_GAP = np.array([b < 128 and not chr(b).isalnum() for b in range(256)])


def words_of(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the lower-case alphanumeric words of texts, and the n + 1 offsets of the texts."""
    parts = [(t or "").lower().encode("utf-8", "surrogatepass") for t in texts]
    raw = np.frombuffer(b"\n".join(parts) + b"\n", dtype=np.uint8)
    starts, ends = word_spans(raw, _GAP)
    at = np.zeros(len(parts) + 1, dtype=np.int64)
    np.cumsum(np.fromiter((len(p) + 1 for p in parts), dtype=np.int64, count=len(parts)), out=at[1:])
    return word_hashes(raw, starts, ends), np.searchsorted(starts, at)


def grams(words: np.ndarray, n: int) -> np.ndarray:
    if len(words) < n:
        return np.zeros(0, dtype=np.uint64)
    return joined([words[i : len(words) - n + 1 + i] for i in range(n)])


@dataclass
class Items:
    """Benchmark items of one block and their n-grams as sorted arrays."""

    ids: list
    words: list[np.ndarray]
    gram: np.ndarray = field(default_factory=lambda: np.zeros(0, np.uint64))  # sorted
    item: np.ndarray = field(default_factory=lambda: np.zeros(0, np.int64))
    place: np.ndarray = field(default_factory=lambda: np.zeros(0, np.int64))
    short: dict[int, dict[int, list[int]]] = field(default_factory=dict)  # short items by number of words and hash of them all

    @classmethod
    def of(cls, rows: list[tuple], rules: Rules) -> Items:
        ids, words = [], []
        for item_id, text in sorted(rows, key=lambda r: (r[0] is None, r[0])):
            w, _ = words_of([text])
            if len(w):
                ids.append(item_id)
                words.append(w)
        self = cls(ids, words)
        if ids:
            few = max(rules.least_words, rules.n)
            for k, w in enumerate(words):
                if len(w) < few:
                    self.short.setdefault(len(w), {}).setdefault(int(grams(w, len(w))[0]), []).append(k)
            g = [grams(w, rules.n) if len(w) >= few else w[:0] for w in words]
            gram = np.concatenate(g)
            item = np.repeat(np.arange(len(g)), [len(x) for x in g])
            place = np.concatenate([np.arange(len(x)) for x in g])
            order = np.argsort(gram, kind="stable")
            self.gram, self.item, self.place = gram[order], item[order], place[order]
        return self

    def sieve(self) -> np.ndarray:
        marks = np.zeros(1 << 20, dtype=bool)
        marks[self.gram & np.uint64((1 << 20) - 1)] = True
        return marks

    def find(self, g: np.ndarray, marks: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Positions in g of n-grams that the items have, and where each first stands in ``gram``."""
        maybe = np.flatnonzero(marks[g & np.uint64((1 << 20) - 1)])
        if not len(maybe) or not len(self.gram):
            return maybe[:0], maybe[:0]
        at = np.searchsorted(self.gram, g[maybe])
        same = self.gram[np.minimum(at, len(self.gram) - 1)] == g[maybe]
        return maybe[same], at[same]


def align(item: np.ndarray, window: np.ndarray, penalty: float) -> tuple[float, int]:
    """Best local alignment score and its end in the window; rows of the matrix are vectors.

    Gaps along the window are a running maximum: score[j] = max over k <= j of
    open[k] - penalty * (j - k).
    """
    drift = penalty * np.arange(len(window) + 1)
    row = np.zeros(len(window) + 1)
    best, end = 0.0, 0
    for w in item:
        now = np.maximum(row - penalty, 0)
        now[1:] = np.maximum(now[1:], row[:-1] + np.where(window == w, 1.0, -penalty))
        row = np.maximum.accumulate(now + drift) - drift
        top = int(row.argmax())
        if row[top] > best:
            best, end = float(row[top]), top
    return best, end


def search(words: np.ndarray, items: Items, marks: np.ndarray, rules: Rules) -> list[tuple[int, float, int, int, int]]:
    """(item number, score, first word, end word, seeds) of contaminating passages in one document."""
    found = _whole(words, items)
    where, at = items.find(grams(words, rules.n), marks)
    if not len(where):
        return [found[k] for k in sorted(found)]
    last = np.searchsorted(items.gram, items.gram[at], side="right")
    count = last - at
    pos = np.repeat(where, count)
    row = np.repeat(at, count) + (np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count))
    item, place = items.item[row], items.place[row]
    diagonal = pos - place
    order = np.lexsort((pos, diagonal, item))
    item, diagonal, place, pos = item[order], diagonal[order], place[order], pos[order]
    sizes = np.array([len(w) for w in items.words])
    cut = np.flatnonzero((np.diff(item) != 0) | (np.diff(diagonal) > np.maximum(4, sizes[item[1:]] // 3))) + 1
    for a, b in zip([0, *cut], [*cut, len(item)], strict=True):
        k = int(item[a])
        seeds = len(np.unique(place[a:b]))
        m = int(sizes[k])
        if seeds < min(rules.least_seeds, m - rules.n + 1):
            continue
        slack = m // 3 + 4
        lo, hi = max(0, int(diagonal[a]) - slack), min(len(words), int(diagonal[b - 1]) + m + slack)
        score, end = align(items.words[k], words[lo:hi], rules.penalty)
        score /= m
        if score >= rules.least_score and (k not in found or score > found[k][1]):
            back, length = align(items.words[k][::-1], words[lo : lo + end][::-1], rules.penalty)
            found[k] = (k, score, lo + end - length, lo + end, seeds)
    return [found[k] for k in sorted(found)]


def _whole(words: np.ndarray, items: Items) -> dict[int, tuple]:
    """The first place of each short item that stands whole in a document."""
    found: dict[int, tuple] = {}
    for n, kinds in items.short.items():
        g = grams(words, n)
        for p in np.flatnonzero(np.isin(g, np.fromiter(kinds, dtype=np.uint64, count=len(kinds)))):
            for k in kinds[int(g[p])]:
                found.setdefault(k, (k, 1.0, int(p), int(p) + n, 1))
    return found


def _blocks(benchmark: DataFrame, item_col: str, text_col: str, rules: Rules):
    """The benchmark in blocks of bounded size, as rows on the driver one block at a time."""
    rows = benchmark.select(F.col(item_col).alias("id"), F.col(text_col).alias("text")).filter(F.col("text").isNotNull())
    words = rows.agg(F.sum(F.length("text"))).first()[0] or 0
    n = max(1, -(-int(words) // (6 * rules.block_words)))
    for b in range(n):
        part = rows if n == 1 else rows.filter(F.pmod(F.xxhash64("id", "text"), F.lit(n)) == b)
        yield [(r[0], r[1]) for r in part.collect()]


def contaminated(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text", rules: Rules = Rules()) -> DataFrame:
    """(id, item_id, score, first_word, end_word, seeds): one row per document and item that it holds.

    The benchmark is the query set: it comes in blocks of bounded size, and every block is
    held against all documents in one pass without a shuffle, which finds seeds and aligns
    around them.  Null and
    empty texts hold nothing; items below ``least_words`` words count where they stand whole; items without words are
    left out; repeated rows each give their rows; empty tables give none.  Whole texts are
    searched; words are lower-case alphanumeric runs, places are word numbers.
    """
    spark = docs.sparkSession
    kind = docs.schema[id_col].dataType.simpleString()
    item_kind = benchmark.schema[item_col].dataType
    schema = f"id {kind}, item {item_kind.simpleString()}, score double, first_word long, end_word long, seeds long"
    out = spark.createDataFrame([], schema)
    for rows in _blocks(benchmark, item_col, item_text, rules):
        items = Items.of(rows, rules)
        if not items.ids:
            continue
        out = out.unionByName(docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).mapInArrow(_searcher(items, rules, item_kind), schema))
    return out.withColumnRenamed("id", id_col).withColumnRenamed("item", item_col)


def _searcher(items: Items, rules: Rules, item_kind):
    from pyspark.sql.pandas.types import to_arrow_type

    item_type = to_arrow_type(item_kind)

    def run(batches):
        import pyarrow as pa

        marks = items.sieve()
        for part in blocks(batches, "text"):
            words, at = words_of(part.column(1).to_pylist())
            rows, found = [], []
            for i in range(part.num_rows):
                for hit in search(words[at[i] : at[i + 1]], items, marks, rules):
                    rows.append(i)
                    found.append((items.ids[hit[0]], *hit[1:]))
            columns = list(zip(*found, strict=True)) if found else [[]] * 5
            kinds = [item_type, pa.float64(), pa.int64(), pa.int64(), pa.int64()]
            yield pa.RecordBatch.from_arrays(
                [part.column(0).take(pa.array(rows, pa.int64())), *(pa.array(c, k) for c, k in zip(columns, kinds, strict=True))],
                names=["id", "item", "score", "first_word", "end_word", "seeds"],
            )

    return tidy(run)


def clean(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text", rules: Rules = Rules()) -> DataFrame:
    """The documents that hold no benchmark item, with all their columns; each row is judged by its own text, without a shuffle."""
    at = docs.columns.index(text_col)
    for rows in _blocks(benchmark, item_col, item_text, rules):
        items = Items.of(rows, rules)
        if items.ids:
            docs = docs.mapInArrow(_sieve(items, rules, at), docs.schema)
    return docs


def _sieve(items: Items, rules: Rules, column: int):
    def run(batches):
        import pyarrow as pa

        marks = items.sieve()
        for part in blocks(batches, column):
            words, at = words_of(part.column(column).to_pylist())
            free = [not search(words[at[i] : at[i + 1]], items, marks, rules) for i in range(part.num_rows)]
            yield part.filter(pa.array(free))

    return tidy(run)
