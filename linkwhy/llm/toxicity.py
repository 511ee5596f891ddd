"""Operator 5: toxicity by a classifier chain of sparse linear models with out-of-fold predictions."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import blocks, lowered, word_hashes, word_spans

BUCKETS = 1 << 18
#: A word counts by itself and by its first bytes, so that inflected and joined forms share evidence.
PREFIXES = (4, 5, 6)
#: The classifier is fitted on about this many labelled documents with, and without, the last category.
SAMPLE = 3000
#: ... whose texts have about this many bytes together at most; the driver gets fewer.
SAMPLE_BYTES = 64 << 20
FOLDS = 3


def features(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """(text number, bucket) for each distinct bucket of each text."""
    parts = [(t or "").encode("utf-8", "surrogatepass") for t in texts]
    raw = lowered(b"\n".join(parts) + b"\n")
    starts, ends = word_spans(raw)
    at = np.cumsum([0, *(len(p) + 1 for p in parts)])
    of = np.searchsorted(at, starts, side="right") - 1
    rows, buckets = [of], [word_hashes(raw, starts, ends)]
    for k in PREFIXES:
        long = ends - starts > k
        s = starts[long]
        rows.append(of[long])
        buckets.append(word_hashes(raw, s, s + k) ^ np.uint64(k))
    return np.concatenate(rows), (np.concatenate(buckets) % np.uint64(BUCKETS)).astype(np.int64)


def distinct(row: np.ndarray, bucket: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    key = np.unique(row * BUCKETS + bucket)
    return key // BUCKETS, key % BUCKETS


@dataclass
class Linear:
    """A sparse logistic model over present buckets and the earlier categories' probabilities."""

    weights: np.ndarray
    chain: np.ndarray
    bias: float

    def odds(self, row: np.ndarray, bucket: np.ndarray, earlier: np.ndarray) -> np.ndarray:
        return self.bias + np.bincount(row, weights=self.weights[bucket], minlength=len(earlier)) + earlier @ self.chain


def probability(odds: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(odds, -35, 35)))


def train_linear(docs: list[np.ndarray], earlier: np.ndarray, y: np.ndarray, epochs: int = 3, alpha: float = 0.1, l1: float = 1.5, seed: int = 3) -> Linear:
    """Follow the regularised leader with per-weight rates; l1 leaves most buckets at zero."""
    z, n = np.zeros(BUCKETS), np.zeros(BUCKETS)
    k = earlier.shape[1]
    dz, dn = np.zeros(k + 1), np.zeros(k + 1)
    rng = np.random.default_rng(seed)

    def weight(z, n, l1):
        return np.where(np.abs(z) <= l1, 0.0, -(z - np.sign(z) * l1) / ((1 + np.sqrt(n)) / alpha + 0.01))

    for _ in range(epochs):
        for i in rng.permutation(len(docs)):
            at, x = docs[i], np.append(earlier[i], 1.0)
            za, na = z[at], n[at]
            w, dw = weight(za, na, l1), weight(dz, dn, 0.0)
            p = 1 / (1 + np.exp(-np.clip(w.sum() + dw @ x, -35, 35)))
            g = p - y[i]
            if abs(g) < 1e-4:
                continue
            step = (np.sqrt(na + g * g) - np.sqrt(na)) / alpha
            z[at] = za + g - step * w
            n[at] = na + g * g
            gx = g * x
            dz += gx - (np.sqrt(dn + gx * gx) - np.sqrt(dn)) / alpha * dw
            dn += gx * gx
    dw = weight(dz, dn, 0.0)
    return Linear(weight(z, n, l1), dw[:-1], float(dw[-1]))


@dataclass
class Chain:
    categories: tuple[str, ...]
    models: list[Linear]

    def probabilities(self, row: np.ndarray, bucket: np.ndarray, n: int) -> np.ndarray:
        """n x categories: each model sees the probabilities that the ones before it gave."""
        known = np.zeros((n, 0))
        for m in self.models:
            known = np.c_[known, probability(m.odds(row, bucket, known))]
        return known


def fit_arrays(docs: list[np.ndarray], labels: np.ndarray, categories: tuple[str, ...], folds: int = FOLDS) -> Chain:
    """Fit the chain: a later model is trained on earlier predictions that were made out of fold."""
    fold = np.arange(len(docs)) % folds
    earlier, models = np.zeros((len(docs), 0)), []
    for c in range(len(categories)):
        y = labels[:, c].astype(float)
        models.append(train_linear(docs, earlier, y))
        if c + 1 == len(categories):
            break
        out = np.zeros(len(docs))
        for f in range(folds):
            rest, own = np.flatnonzero(fold != f), np.flatnonzero(fold == f)
            if len(rest) and len(own):
                m = train_linear([docs[i] for i in rest], earlier[rest], y[rest])
                row = np.repeat(np.arange(len(own)), [len(docs[i]) for i in own])
                out[own] = probability(m.odds(row, np.concatenate([docs[i] for i in own]), earlier[own]))
        earlier = np.c_[earlier, out]
    return Chain(categories, models)


def fit(docs: DataFrame, labels: DataFrame, categories: dict[str, str], id_col: str = "doc_id", text_col: str = "text", sample: int = SAMPLE, sample_bytes: int = SAMPLE_BYTES) -> Chain | None:
    """Fit on a bounded sample of labelled rows, drawn by a hash of the id.

    ``categories`` maps each category, in chain order, to a boolean SQL expression over the
    label columns.  About ``sample`` rows with the last category and ``sample`` without are
    taken, fewer if their texts have more than ``sample_bytes``; rows with a null label are not learnt
    from.  None if nothing is labelled.
    """
    names = tuple(categories)
    marked = labels.select(F.col(id_col).alias("__id"), *(F.expr(e).cast("int").alias(f"c{i}") for i, e in enumerate(categories.values())))
    last = f"c{len(names) - 1}"
    marked = marked.dropna()
    counts = {r[0]: r[1] for r in marked.groupBy(last).agg(F.count(F.lit(1))).collect()}
    if not counts:
        return None
    share = F.create_map(*(x for k, n in counts.items() for x in (F.lit(k), F.lit(int(1_000_000 * min(1.0, sample / n))))))
    chosen = marked.filter(F.pmod(F.xxhash64("__id"), F.lit(1_000_000)) < share[F.col(last)])
    # a bounded sample: about 2 * sample rows of a few integers
    found = docs.select(F.col(id_col).alias("__id"), F.col(text_col).alias("text")).join(F.broadcast(chosen), "__id")
    size = found.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    if size > sample_bytes:
        found = found.filter(F.pmod(F.xxhash64(F.lit(1), "__id"), F.lit(1_000_000)) < int(1_000_000 * sample_bytes / size))
    columns = [f"c{i}" for i in range(len(names))]

    def extract(batches):
        import pyarrow as pa

        for part in blocks(batches, "text"):
            row, bucket = distinct(*features(part.column(part.schema.get_field_index("text")).to_pylist()))
            cuts = np.searchsorted(row, np.arange(part.num_rows + 1))
            data = [bucket[a:b].astype("<i4").tobytes() for a, b in zip(cuts, cuts[1:], strict=False)]
            yield pa.RecordBatch.from_arrays([part.column(part.schema.get_field_index(c)) for c in ["__id", *columns]] + [pa.array(data, pa.binary())], names=["__id", *columns, "x"])

    kind = docs.schema[id_col].dataType.simpleString()
    rows = found.select("__id", "text", *columns).mapInArrow(extract, f"__id {kind}, " + ", ".join(f"{c} int" for c in columns) + ", x binary").collect()
    if not rows:
        return None
    rows.sort(key=lambda r: (str(r[0]), bytes(r[-1])))
    order = np.random.default_rng(5).permutation(len(rows))
    rows = [rows[i] for i in order]
    return fit_arrays([np.frombuffer(bytes(r[-1]), "<i4").astype(np.int64) for r in rows], np.array([list(r[1:-1]) for r in rows]), names)


def predict(docs: DataFrame, chain: Chain | None, categories: tuple[str, ...], id_col: str = "doc_id", text_col: str = "text", threshold: float = 0.5) -> DataFrame:
    """(id, p_<category> for each, and a boolean named as the last category) for every whole text.

    Null and empty texts have no features: probabilities 0 and not in the category; so has
    every text if nothing was labelled.  Repeated rows each give a row; an empty table
    gives none.  No shuffle.
    """
    base = docs.select(F.col(id_col).alias("__id"), F.col(text_col).alias("text"))
    names = [f"p_{c}" for c in categories]
    sparse = None
    if chain is not None:
        used = np.flatnonzero(np.any([m.weights != 0 for m in chain.models], axis=0))
        sparse = (used, np.array([m.weights[used] for m in chain.models]), [(m.chain, m.bias) for m in chain.models])

    def run(batches):
        import pyarrow as pa

        if sparse is not None:
            used, weights, rest = sparse
            at = np.full(BUCKETS, -1)
            at[used] = np.arange(len(used))
            small = Chain(categories, [Linear(w, c, b) for w, (c, b) in zip(weights, rest, strict=True)])
        for part in blocks(batches, "text"):
            texts = part.column(1).to_pylist()
            p = np.zeros((len(texts), len(names)))
            if sparse is not None:
                row, bucket = features(texts)
                live = at[bucket] >= 0
                row, bucket = distinct(row[live], bucket[live])
                p = small.probabilities(row, at[bucket], len(texts))
                p[[not (t and t.strip()) for t in texts]] = 0
            yield pa.RecordBatch.from_arrays([part.column(0), *(pa.array(p[:, i]) for i in range(len(names)))], names=["__id", *names])

    kind = base.schema["__id"].dataType.simpleString()
    out = base.mapInArrow(run, f"`__id` {kind}, " + ", ".join(f"{n} double" for n in names))
    return out.select(F.col("__id").alias(id_col), *names, (F.col(names[-1]) >= threshold).alias(categories[-1]))
