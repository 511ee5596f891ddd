"""Operator 3: an interpolated modified Kneser-Ney bigram model, counted in Spark.

The model is a set of files of sorted 64-bit hashes in the shared folder: words with their
counts and numbers of distinct left neighbours, contexts with their totals and counts of
successors seen once, twice and more, and bigrams with their counts.  Files are shards by
hash; workers map them into memory and look up the sorted hashes of a block of text.
"""

from __future__ import annotations

import zlib
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import store
from .common import blocks, document_words, joined, mix, shared_dir

#: The token that ends every text, and the context before its first token.
END, START = np.uint64(0x5BD1E9955BD1E995), np.uint64(0x27D4EB2F165667C5)
#: Bigram tokens for each shard, about; a shard must fit one task.
SHARD_TOKENS = 2_500_000
#: A context with more than this share of all tokens has its successors spread over all shards.
HEAVY_SHARE = 1 / 512
#: Tokens that a task gathers before it sends counts on.
GATHER = 3_000_000


@dataclass(frozen=True)
class Model:
    base: str
    words: int  # shards of words
    bigrams: int  # shards of bigrams
    tokens: int  # N
    types: int  # V
    heavy: np.ndarray  # sorted contexts that are spread
    heavy_stats: np.ndarray  # total, successors once, twice, more
    discounts: np.ndarray  # bigrams: for counts 1, 2, 3 and more
    low_discounts: np.ndarray  # words, by numbers of left neighbours
    low_total: int
    low_gamma: float


def token_arrays(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Tokens of the texts with END behind each, the token before each (START first), and the offsets."""
    words, at = document_words(texts)
    n = np.diff(at)
    token = np.insert(words, at[1:], END)
    offsets = np.zeros(len(at), dtype=np.int64)
    np.cumsum(n + 1, out=offsets[1:])
    before = np.empty_like(token)
    before[1:] = token[:-1]
    before[offsets[:-1]] = START
    return token, before, offsets


def _tally(keys: np.ndarray, weights: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct keys and their summed weights."""
    if not len(keys):
        return keys, np.zeros(0, dtype=np.int64)
    order = np.argsort(keys)
    keys = keys[order]
    first = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]])
    if weights is None:
        return keys[first], np.diff(np.r_[first, len(keys)])
    return keys[first], np.add.reduceat(weights[order], first)


def _shard(keys: np.ndarray, n: int) -> np.ndarray:
    return ((keys >> np.uint64(20)) % np.uint64(n)).astype(np.int64)


def _spread(context: np.ndarray, word: np.ndarray, heavy: np.ndarray, n: int) -> np.ndarray:
    """The shard of bigrams: by context, or by both words where the context is heavy."""
    key = context.copy()
    if len(heavy):
        at = np.minimum(np.searchsorted(heavy, context), len(heavy) - 1)
        own = heavy[at] == context
        key[own] = mix(context[own] ^ word[own])
    return _shard(key, n)


def _pack(*arrays: np.ndarray) -> bytes:
    return b"".join(len(b).to_bytes(8, "little") + b for b in (a.tobytes() for a in arrays))


def _small(counts: np.ndarray) -> np.ndarray:
    """Counts, mostly one, squeezed for the shuffle."""
    return np.frombuffer(zlib.compress(counts.astype("<u4").tobytes(), 1), dtype=np.uint8)


def _unsmall(raw: np.ndarray) -> np.ndarray:
    return np.frombuffer(zlib.decompress(raw.tobytes()), dtype="<u4").astype(np.int64)


def _unpack(data: bytes, *kinds) -> list[np.ndarray]:
    out, at = [], 0
    for kind in kinds:
        size = int.from_bytes(data[at : at + 8], "little")
        out.append(np.frombuffer(data, dtype=kind, count=size // np.dtype(kind).itemsize, offset=at + 8))
        at += 8 + size
    return out


_PAYLOAD = "shard long, payload binary"
_STATS = "kind string, k long, a long, b long, c long, d long"


def _payloads(rows):
    import pyarrow as pa

    return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.binary())], names=["shard", "payload"])


def _stats(rows):
    import pandas as pd

    return pd.DataFrame(rows, columns=["kind", "k", "a", "b", "c", "d"])


def _below_four(counts: np.ndarray) -> list[int]:
    return [int((counts == i).sum()) for i in (1, 2, 3, 4)]


def _discounts(n: list[int]) -> np.ndarray:
    """Modified Kneser-Ney discounts from how many keys were seen once to four times."""
    n1, n2, n3, n4 = (float(x) for x in n)
    if not n1 or not n2:
        return np.array([0.5, 0.75, 0.9])
    y = n1 / (n1 + 2 * n2)
    d = [1 - 2 * y * n2 / n1, 2 - 3 * y * n3 / n2 if n3 else 1.0, 3 - 4 * y * n4 / n3 if n3 and n4 else 1.5]
    return np.array([min(max(x, 0.05), i + 0.95) for i, x in enumerate(d)])


def _summed(stats: DataFrame) -> list:
    """Totals by kind and key: a few fixed kinds, and one row for each heavy context (a bounded number)."""
    return stats.groupBy("kind", "k").agg(*(F.sum(c).alias(c) for c in "abcd")).collect()


def fit(docs: DataFrame, learnable: Column, text_col: str = "text") -> Model:
    """Count the learnable texts and write the model to the shared folder.

    Two passes over the texts: words, then bigrams (the first finds the heavy contexts).
    Within a task, equal keys are summed before they are sent on as sorted blocks; no
    group is larger than a shard, since heavy contexts are spread.  The driver gets counters
    and fewer than 1 / HEAVY_SHARE heavy contexts.
    """
    spark = docs.sparkSession
    base = shared_dir(spark) + "-lm"
    texts = docs.filter(learnable).select(F.col(text_col).alias("text"))
    words = max(4, 2 * texts.rdd.getNumPartitions())

    def count_words(batches):
        keys, counts, held = [], [], 0
        for part in blocks(batches, "text"):
            token, _, _ = token_arrays(part.column(0).to_pylist())
            k, c = _tally(token)
            keys.append(k)
            counts.append(c)
            held += len(k)
            if held > GATHER:
                k, c = _tally(np.concatenate(keys), np.concatenate(counts))
                yield _payloads(_by_shard(_shard(k, words), k, c))
                keys, counts, held = [], [], 0
        if keys:
            k, c = _tally(np.concatenate(keys), np.concatenate(counts))
            yield _payloads(_by_shard(_shard(k, words), k, c))

    def store_words(key, frame):
        parts = [_unpack(p, "<u8", np.uint8) for p in frame["payload"]]
        k, c = _tally(np.concatenate([p[0] for p in parts]), np.concatenate([_unsmall(p[1]) for p in parts]))
        store.put(base, f"w{key[0]}", {"key": k, "count": c})
        big = np.argsort(c)[::-1][:2048]  # a word above the heavy share of all is among the largest of its shard
        rows = [("all", 0, int(c.sum()), len(k), 0, 0)]
        return _stats(rows + [("big", int(k[i].view(np.int64)), int(c[i]), 0, 0, 0) for i in big if c[i] * 2048 >= c.sum()])

    first = texts.mapInArrow(count_words, _PAYLOAD).groupBy("shard").applyInPandas(store_words, _STATS)
    first = first.groupBy("kind", "k").agg(F.sum("a").alias("a"), F.sum("b").alias("b"))
    total = first.filter("kind = 'all'")
    # one scan: the heavy candidates are compared with the total after a bounded read
    rows = first.orderBy(F.col("kind"), F.col("a").desc()).limit(1 + int(1 / HEAVY_SHARE)).collect()
    del total
    tokens, types = next(((int(r["a"]), int(r["b"])) for r in rows if r["kind"] == "all"), (0, 0))
    heavy = np.array(sorted({r["k"] % (1 << 64) for r in rows if r["kind"] == "big" and r["a"] > HEAVY_SHARE * tokens} | {int(START)}), dtype=np.uint64)
    shards = max(1, -(-tokens // SHARD_TOKENS))

    def count_bigrams(batches):
        held, contexts, nexts = 0, [], []

        def send():
            context, word = np.concatenate(contexts), np.concatenate(nexts)
            key = joined([context, word])
            order = np.argsort(key)
            begin = np.flatnonzero(np.r_[True, np.diff(key[order]) != 0])
            pick = order[begin]
            return _by_context(_spread(context[pick], word[pick], heavy, shards), context[pick], word[pick], np.diff(np.r_[begin, len(key)]))

        for part in blocks(batches, "text"):
            token, before, _ = token_arrays(part.column(0).to_pylist())
            contexts.append(before)
            nexts.append(token)
            held += len(token)
            if held > GATHER:
                yield _payloads(send())
                held, contexts, nexts = 0, [], []
        if held:
            yield _payloads(send())

    def store_bigrams(key, frame):
        import pandas as pd

        parts = [_unpack(p, "<u8", "<u4", "<u8", np.uint8) for p in frame["payload"]]
        context = np.concatenate([np.repeat(p[0], p[1]) for p in parts])
        word = np.concatenate([p[2] for p in parts])
        count = np.concatenate([_unsmall(p[3]) for p in parts])
        both = joined([context, word])
        order = np.argsort(both)
        begin = np.flatnonzero(np.r_[True, np.diff(both[order]) != 0])
        both, pick = both[order][begin], order[begin]
        count = np.add.reduceat(count[order], begin)
        context, word = context[pick], word[pick]
        by = np.argsort(context, kind="stable")
        start = np.flatnonzero(np.r_[True, np.diff(context[by]) != 0])
        c = count[by]
        stats = np.stack([np.add.reduceat(x.astype(np.int64), start) for x in (c, c == 1, c == 2, c >= 3)], axis=1)
        ctx = context[by][start]
        at = np.minimum(np.searchsorted(heavy, ctx), len(heavy) - 1)
        is_heavy = heavy[at] == ctx
        store.put(base, f"b{key[0]}", {"key": both, "count": count.astype(np.uint32), "context": ctx[~is_heavy], "stats": stats[~is_heavy].astype(np.uint32)})
        k, n = _tally(word)
        out = [(s, p, "left", 0, 0, 0, 0, 0) for s, p in _by_shard(_shard(k, words), k, n)]
        out += [(-1, None, "heavy", int(h.view(np.int64)), *(int(x) for x in row)) for h, row in zip(ctx[is_heavy], stats[is_heavy], strict=True)]
        out.append((-1, None, "seen", 0, *_below_four(count)))
        out = pd.DataFrame(out, columns=["shard", "payload", "kind", "k", "a", "b", "c", "d"])
        out.loc[out["shard"] < 0, "shard"] = -1 - key[0] % 64  # counters pass in groups of their own
        return out

    def store_left(key, frame):
        if key[0] < 0:
            return frame.groupby(["kind", "k"], as_index=False)[["a", "b", "c", "d"]].sum()
        parts = [_unpack(p, "<u8", np.uint8) for p in frame["payload"]]
        k, n = _tally(np.concatenate([p[0] for p in parts]), np.concatenate([_unsmall(p[1]) for p in parts]))
        own = store.mapped(base, f"w{key[0]}", "key")
        left = np.zeros(len(own), dtype=np.int64)
        left[np.searchsorted(own, k)] = n
        store.put(base, f"w{key[0]}", {"left": left})
        return _stats([("left", 0, *_below_four(left)), ("sum", 0, int(left.sum()), int((left >= 3).sum()), 0, 0)])

    counted = texts.mapInArrow(count_bigrams, _PAYLOAD).groupBy("shard").applyInPandas(store_bigrams, f"{_PAYLOAD}, {_STATS}")
    found = {(r["kind"], r["k"]): [int(r[c]) for c in "abcd"] for r in _summed(counted.groupBy("shard").applyInPandas(store_left, _STATS))} if tokens else {}
    stats = {k % (1 << 64): v for (kind, k), v in found.items() if kind == "heavy"}
    heavy_stats = np.array([stats.get(int(h), [0, 0, 0, 0]) for h in heavy], dtype=np.float64).reshape(-1, 4)
    left = found.get(("left", 0), [0] * 4)
    low_total, three = found.get(("sum", 0), [0] * 4)[:2]
    low = _discounts(left)
    gamma = float(low @ np.array([left[0], left[1], three])) / low_total if low_total else 1.0
    return Model(base, words, shards, tokens, types, heavy, heavy_stats, _discounts(found.get(("seen", 0), [0] * 4)), low, low_total, gamma)


def _by_shard(shard: np.ndarray, keys: np.ndarray, counts: np.ndarray):
    order = np.argsort(shard, kind="stable")
    cuts = np.flatnonzero(np.r_[True, np.diff(shard[order]) != 0, True]) if len(order) else np.zeros(1, int)
    return [(int(shard[order[a]]), _pack(keys[order[a:b]], _small(counts[order[a:b]]))) for a, b in zip(cuts, cuts[1:], strict=False)]


def _by_context(shard: np.ndarray, context: np.ndarray, word: np.ndarray, counts: np.ndarray):
    """Blocks for each shard, sorted by context so that each context is sent once."""
    order = np.lexsort((context, shard))
    shard, context, word, counts = shard[order], context[order], word[order], counts[order]
    cuts = np.flatnonzero(np.r_[True, np.diff(shard) != 0, True])
    out = []
    for a, b in zip(cuts, cuts[1:], strict=False):
        begin = np.flatnonzero(np.r_[True, np.diff(context[a:b]) != 0])
        out.append((int(shard[a]), _pack(context[a:b][begin], np.diff(np.r_[begin, b - a]).astype("<u4"), word[a:b], _small(counts[a:b]))))
    return out


class Scorer:
    """Looks up a block of tokens in the mapped files."""

    MOST_MAPS = 256

    def __init__(self, model: Model):
        self.model = model
        self.maps: dict[tuple[str, str], np.ndarray | None] = {}

    def _map(self, name: str, key: str):
        if (name, key) not in self.maps:
            if len(self.maps) >= self.MOST_MAPS:
                self.maps.clear()
            self.maps[name, key] = store.mapped(self.model.base, name, key)
        return self.maps[name, key]

    def _look(self, prefix: str, shard: np.ndarray, keys: np.ndarray, index: str, values: list[str], width: int) -> np.ndarray:
        """Values (n x width) of keys by shard; zero where a key is missing.  Keys come sorted within a shard."""
        out = np.zeros((len(keys), width))
        order = np.lexsort((keys, shard))
        cuts = np.flatnonzero(np.r_[True, np.diff(shard[order]) != 0, True]) if len(order) else [0]
        for a, b in zip(cuts, cuts[1:], strict=False):
            rows = order[a:b]
            name = f"{prefix}{int(shard[rows[0]])}"
            own = self._map(name, index)
            if own is None or not len(own):
                continue
            at = np.searchsorted(own, keys[rows])
            same = own[np.minimum(at, len(own) - 1)] == keys[rows]
            if not same.any():
                continue
            col = 0
            for v in values:
                found = self._map(name, v)
                if found is None:
                    continue
                found = found[at[same]]
                found = found.reshape(len(found), -1)
                out[rows[same], col : col + found.shape[1]] = found
                col += found.shape[1]
        return out

    def score(self, token: np.ndarray, before: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Count of each token and its log10 probability."""
        m = self.model
        kinds, of = np.unique(token, return_inverse=True)
        word = self._look("w", _shard(kinds, m.words), kinds, "key", ["count", "left"], 2)
        count, left = word[of, 0], word[of, 1]
        d = np.r_[0.0, m.low_discounts][np.minimum(left, 3).astype(int)]
        low = m.low_gamma / (m.types + 1) + (np.maximum(left - d, 0) / m.low_total if m.low_total else 0.0)

        key = joined([before, token])
        pairs, first, back = np.unique(key, return_index=True, return_inverse=True)
        shard = _spread(before[first], token[first], m.heavy, m.bigrams)
        seen = self._look("b", shard, pairs, "key", ["count"], 1)[back, 0]

        contexts, which = np.unique(before, return_inverse=True)
        stats = self._look("b", _shard(contexts, m.bigrams), contexts, "context", ["stats"], 4)
        at = np.minimum(np.searchsorted(m.heavy, contexts), len(m.heavy) - 1)
        own = m.heavy[at] == contexts
        stats[own] = m.heavy_stats[at[own]]
        total = stats[:, 0]
        gamma = np.where(total > 0, (stats[:, 1:] @ m.discounts) / np.maximum(total, 1), 1.0)
        d = np.r_[0.0, m.discounts][np.minimum(seen, 3).astype(int)]
        p = np.maximum(seen - d, 0) / np.maximum(total, 1)[which] + gamma[which] * low
        return count, np.log10(p)


_SCORERS: dict[str, Scorer] = {}


def score(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text", keep: tuple[str, ...] = ()) -> DataFrame:
    """(id, *keep, n_tokens, n_known, train_tokens, base_score, score, perplexity) for every whole text.

    Null and empty texts are the end token alone.  An empty training set gives every token
    probability 1 / (0 + 1).  Repeated rows each give a row; an empty table gives none.  No
    shuffle: the workers map the model files.
    """
    names = ["n_tokens", "n_known", "train_tokens", "base_score", "score"]
    keep = tuple(k for k in keep if k not in (id_col, "perplexity", *names))  # an output's name goes to the output
    base = docs.select(F.col(id_col).alias("__id"), F.col(text_col).alias("__text"), *keep)
    kinds = {f.name: f.dataType.simpleString() for f in base.schema.fields}

    def run(batches):
        import pyarrow as pa

        if model.base not in _SCORERS:
            _SCORERS.clear()
            _SCORERS[model.base] = Scorer(model)
        scorer = _SCORERS[model.base]
        floor = np.log10(model.tokens + 0.5 * (model.types + 1))
        for part in blocks(batches, "__text"):
            token, before, at = token_arrays(part.column(1).to_pylist())
            count, logp = scorer.score(token, before)
            sums = [np.add.reduceat(x, at[:-1]) for x in ((count > 0).astype(np.int64), np.log10(count + 0.5) - floor, logp)]
            kept = [part.column(i) for i in range(part.num_columns) if i != 1]
            arrays = [pa.array(np.diff(at)), pa.array(sums[0]), pa.array(np.full(part.num_rows, model.tokens)), pa.array(sums[1]), pa.array(sums[2])]
            yield pa.RecordBatch.from_arrays([*kept, *arrays], names=["__id", *keep, *names])

    schema = ", ".join(f"`{n}` {kinds[n]}" for n in ["__id", *keep]) + ", n_tokens long, n_known long, train_tokens long, base_score double, score double"
    out = base.mapInArrow(run, schema)
    return out.select(F.col("__id").alias(id_col), *keep, *names, F.pow(F.lit(10.0), -F.col("score") / F.col("n_tokens")).alias("perplexity"))
