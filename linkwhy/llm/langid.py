"""Operator 2: language identification by a byte convolutional network, trained in numpy."""

from __future__ import annotations

import functools
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import blocks, tidy

WINDOW = 256
WIDTHS = (2, 3, 4)
#: The classifier is fitted on about this many documents of each language, with so many windows of each.
SAMPLE_DOCS = 700
SAMPLE_WINDOWS = 6
UNKNOWN = "und"


@dataclass(frozen=True)
class ByteNet:
    """Weights: byte embedding, one filter bank for each width, and the softmax layer."""

    labels: tuple[str, ...]
    embedding: np.ndarray  # 256 x e; row 0 stands for padding
    filters: tuple[np.ndarray, ...]  # width x e x f
    biases: tuple[np.ndarray, ...]  # f
    dense: np.ndarray  # (widths * f) x labels
    offset: np.ndarray  # labels

    @functools.cached_property
    def tables(self):
        """Responses by byte and by pair of bytes: a filter is a sum of look-ups."""
        out = []
        for w in self.filters:
            by_byte = [self.embedding @ w[j] for j in range(len(w))]
            parts = []
            for j in range(0, len(w), 2):
                if j + 1 < len(w):
                    both = by_byte[j][:, None, :] + by_byte[j + 1][None, :, :]
                    parts.append((j, True, np.ascontiguousarray(both.reshape(65536, -1), dtype=np.float32)))
                else:
                    parts.append((j, False, np.ascontiguousarray(by_byte[j], dtype=np.float32)))
            out.append((len(w), parts))
        return out

    def windows(self, x: np.ndarray, chunk: int = 256) -> np.ndarray:
        """Class probabilities of windows (n x WINDOW bytes)."""
        return np.concatenate([self._some(x[i : i + chunk]) for i in range(0, len(x), chunk)]) if len(x) else np.zeros((0, len(self.labels)))

    def _some(self, x: np.ndarray) -> np.ndarray:
        single = x.astype(np.intp)
        pair = (single[:, :-1] << 8) | single[:, 1:]
        pooled = []
        for (width, parts), bias in zip(self.tables, self.biases, strict=True):
            n = x.shape[1] - width + 1
            total = None
            for j, two, look in parts:
                got = np.take(look, (pair if two else single)[:, j : j + n], axis=0)
                total = got if total is None else np.add(total, got, out=total)
            pooled.append(np.maximum(total.max(axis=1) + bias, 0))
        z = np.concatenate(pooled, axis=1) @ self.dense + self.offset
        z -= z.max(axis=1, keepdims=True)
        e = np.exp(z)
        return e / e.sum(axis=1, keepdims=True)


def train(x: np.ndarray, y: np.ndarray, labels: tuple[str, ...], epochs: int = 6, e: int = 8, f: int = 8, batch: int = 128, rate: float = 4e-3, seed: int = 7) -> ByteNet:
    """Fit by Adam on cross entropy; gradients pass max pooling only at the largest response."""
    rng = np.random.default_rng(seed)
    p = {"emb": rng.normal(0, 0.3, (256, e)).astype(np.float32), "dense": rng.normal(0, 0.2, (len(WIDTHS) * f, len(labels))).astype(np.float32), "off": np.zeros(len(labels), np.float32)}
    for k in WIDTHS:
        p[f"w{k}"] = rng.normal(0, (2 / (k * e)) ** 0.5, (k * e, f)).astype(np.float32)
        p[f"b{k}"] = np.zeros(f, np.float32)
    first = {k: np.zeros_like(v) for k, v in p.items()}
    second = {k: np.zeros_like(v) for k, v in p.items()}
    step = 0
    for _ in range(epochs):
        order = rng.permutation(len(x))
        for at in range(0, len(x), batch):
            rows = order[at : at + batch]
            xb, yb, n = x[rows].astype(np.intp), y[rows], len(rows)
            emb = p["emb"][xb]
            pooled, kept = [], []
            for k in WIDTHS:
                view = np.lib.stride_tricks.sliding_window_view(emb, k, axis=1).transpose(0, 1, 3, 2).reshape(n, -1, k * e)
                r = view @ p[f"w{k}"]
                top = r.argmax(axis=1)
                v = np.take_along_axis(r, top[:, None, :], axis=1)[:, 0, :] + p[f"b{k}"]
                pooled.append(np.maximum(v, 0))
                kept.append((k, view, top, v > 0))
            hidden = np.concatenate(pooled, axis=1)
            z = hidden @ p["dense"] + p["off"]
            z -= z.max(axis=1, keepdims=True)
            prob = np.exp(z)
            prob /= prob.sum(axis=1, keepdims=True)
            prob[np.arange(n), yb] -= 1
            prob /= n
            g = {"dense": hidden.T @ prob, "off": prob.sum(axis=0), "emb": np.zeros_like(p["emb"])}
            back = prob @ p["dense"].T
            for i, (k, view, top, live) in enumerate(kept):
                d = back[:, i * f : (i + 1) * f] * live
                patch = np.take_along_axis(view, top[:, :, None], axis=1)  # n x f x (k e)
                g[f"w{k}"] = np.einsum("nfk,nf->kf", patch, d)
                g[f"b{k}"] = d.sum(axis=0)
                to = (d[:, :, None] * p[f"w{k}"].T[None]).reshape(n, f, k, e)
                at_bytes = xb[np.arange(n)[:, None, None], top[:, :, None] + np.arange(k)]
                np.add.at(g["emb"], at_bytes.reshape(-1), to.reshape(-1, e))
            step += 1
            for k, v in g.items():
                first[k] += 0.1 * (v - first[k])
                second[k] += 0.001 * (v * v - second[k])
                p[k] -= rate * (first[k] / (1 - 0.9**step)) / (np.sqrt(second[k] / (1 - 0.999**step)) + 1e-7)
    return ByteNet(labels, p["emb"], tuple(p[f"w{k}"].reshape(k, e, f) for k in WIDTHS), tuple(p[f"b{k}"] for k in WIDTHS), p["dense"], p["off"])


def cut(text: str) -> np.ndarray:
    """All windows of a whole text (lower case, UTF-8, the last one padded with zeros)."""
    raw = np.frombuffer(text.lower().encode("utf-8", "surrogatepass"), dtype=np.uint8)
    n = max(1, -(-len(raw) // WINDOW))
    out = np.zeros(n * WINDOW, dtype=np.uint8)
    out[: len(raw)] = raw
    return out.reshape(n, WINDOW)


_LETTER = np.zeros(256, dtype=np.float64)
_LETTER[97:123] = 1
_LETTER[128:] = 1


def fit(docs: DataFrame, learnable: Column, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", sample_docs: int = SAMPLE_DOCS) -> ByteNet | None:
    """Train on a bounded sample of labelled documents: about ``sample_docs`` for each language.

    Rows are drawn by a hash of their id, so the sample is the same on every run.  The
    driver gets the counts by language and ``sample_docs * SAMPLE_WINDOWS`` windows of 256
    bytes for each language.  None if there is no labelled text.
    """
    usable = docs.filter(learnable & F.col(lang_col).isNotNull() & F.col(text_col).isNotNull())
    counts = {r[0]: r[1] for r in usable.groupBy(lang_col).agg(F.count(F.lit(1)).alias("n")).collect()}
    if not counts:
        return None
    labels = tuple(sorted(counts))
    draw = F.pmod(F.xxhash64(F.col(id_col)), F.lit(1_000_000))
    share = F.create_map(*(x for k in labels for x in (F.lit(k), F.lit(int(1_000_000 * min(1.0, sample_docs / counts[k]))))))
    sample = usable.filter(draw < share[F.col(lang_col)]).select(F.col(lang_col).alias("lang"), F.col(text_col).alias("text"))

    def some(batches):
        import pyarrow as pa

        for batch in batches:
            langs, found = [], []
            for lang, t in zip(batch.column(0), batch.column(1), strict=True):
                text = t.as_py()
                if not any(c.isalpha() for c in text):
                    continue
                w = cut(text)
                own = np.random.default_rng(len(text))
                for i in own.permutation(len(w))[:SAMPLE_WINDOWS]:
                    x = w[i].copy()
                    if own.random() < 0.25:  # short texts must be known too
                        x[int(own.integers(24, WINDOW)) :] = 0
                    if _LETTER[x].sum() >= 4:
                        langs.append(lang.as_py())
                        found.append(x.tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(langs, pa.string()), pa.array(found, pa.binary())], names=["lang", "window"])

    rows = sorted((r[0], bytes(r[1])) for r in sample.mapInArrow(some, "lang string, window binary").collect())
    if not rows:
        return None
    labels = tuple(sorted({r[0] for r in rows}))
    x = np.frombuffer(b"".join(r[1] for r in rows), dtype=np.uint8).reshape(-1, WINDOW)
    y = np.array([labels.index(r[0]) for r in rows])
    return train(x, y, labels)


def predict(docs: DataFrame, model: ByteNet | None, id_col: str = "doc_id", text_col: str = "text", keep: tuple[str, ...] = ()) -> DataFrame:
    """(id, *keep, lang_pred, score) for every whole text; a column in ``keep`` with an output's name is left out.

    All windows of a text are judged; their probabilities are averaged with the number of
    letters as weight.  Null, empty and letterless texts give ``und`` and 0, as does every
    text when there was nothing to learn from.  Repeated rows each give a row; an empty
    table gives none.  No shuffle.
    """
    out = judged(docs, model, id_col, text_col, tuple(k for k in keep if k not in (id_col, "lang_pred", "score")))
    return out.withColumnsRenamed({"__id": id_col, "__lang": "lang_pred", "__score": "score"})


def _judge(model: ByteNet | None, texts: list[str | None]) -> tuple[list[str], list[float]]:
    """Language and score of each text."""
    import regex

    letter = regex.compile(r"\p{L}")
    made, of = [], []
    for i, t in enumerate(texts):
        if model is not None and t and letter.search(t):
            w = cut(t)
            made.append(w)
            of.append(np.full(len(w), i))
    langs, scores = [UNKNOWN] * len(texts), [0.0] * len(texts)
    if made:
        x, of = np.concatenate(made), np.concatenate(of)
        weight = _LETTER[x].sum(axis=1) + 1e-3
        total = np.zeros((len(texts), len(model.labels)))
        np.add.at(total, of, model.windows(x) * weight[:, None])
        whole = total.sum(axis=1)
        for i in np.unique(of):
            best = int(total[i].argmax())
            langs[i], scores[i] = model.labels[best], float(min(1.0, total[i, best] / whole[i]))
    return langs, scores


def _verdicts(model: ByteNet | None, column) -> tuple[list[str], list[float]]:
    """Language and score of an Arrow column of texts, judged in parts of bounded size."""
    langs, scores, some, size = [], [], [], 0
    for t in column:
        some.append(t.as_py())
        size += len(some[-1] or "")
        if size > 1 << 20:
            a, b = _judge(model, some)
            langs, scores, some, size = langs + a, scores + b, [], 0
    a, b = _judge(model, some)
    return langs + a, scores + b


def judged(docs: DataFrame, model: ByteNet | None, id_col: str, text_col: str, keep: tuple[str, ...]) -> DataFrame:
    """As ``predict``, with columns __id, *keep, __lang and __score."""
    base = docs.select(F.col(id_col).alias("__id"), F.col(text_col).alias("__text"), *keep)
    kinds = {f.name: f.dataType.simpleString() for f in base.schema.fields}

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            langs, scores = _verdicts(model, batch.column(1))
            kept = [batch.column(i) for i in range(batch.num_columns) if i != 1]
            yield pa.RecordBatch.from_arrays([*kept, pa.array(langs, pa.string()), pa.array(scores, pa.float64())], names=["__id", *keep, "__lang", "__score"])

    schema = ", ".join(f"`{n}` {kinds[n]}" for n in ["__id", *keep]) + ", __lang string, __score double"
    return base.mapInArrow(tidy(run), schema)


def accepted(docs: DataFrame, model: ByteNet | None, id_col: str = "doc_id", text_col: str = "text", least: float = 0.4) -> DataFrame:
    """The documents with a language: not ``und``, and judged with a score of at least ``least``; columns stay.

    Without a model (nothing was labelled) there is nothing to judge by, and every row stays, so that a corpus
    without labels is not lost; ``predict`` calls such texts ``und``.
    """
    if model is None:
        return docs
    at = docs.columns.index(text_col)

    def run(batches):
        import pyarrow as pa

        for part in blocks(batches, at):
            langs, scores = _verdicts(model, part.column(at))
            yield part.filter(pa.array([lang != UNKNOWN and score >= least for lang, score in zip(langs, scores, strict=True)]))

    return docs.mapInArrow(tidy(run), docs.schema)
