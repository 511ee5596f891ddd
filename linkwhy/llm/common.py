"""Helpers that several operators share: table access, checkpoints, word hashing."""

from __future__ import annotations

import os
from urllib.parse import urlparse

import numpy as np
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.runs import delete_later, scratch, settle, shared_dir

__all__ = ["delete_later", "scratch", "settle", "shared_dir"]

#: Words are maximal runs without these bytes: space and the controls 9 to 13.
SPACES = " \t\n\x0b\x0c\r"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables, read by Spark alone so that any store works."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def local_path(uri: str) -> str | None:
    """The path of a ``file:`` URI; None for other stores."""
    parts = urlparse(uri)
    return parts.path if parts.scheme in ("", "file") else None


def mkdirs(path: str) -> None:
    os.makedirs(path, exist_ok=True)


def text_or_empty(name: str = "text") -> Column:
    return F.coalesce(F.col(name), F.lit(""))


def crc_mod(column: str, modulus: int) -> Column:
    """crc32 of a key's decimal text modulo ``modulus`` (null key: of the empty text)."""
    return F.pmod(F.crc32(F.coalesce(F.col(column).cast("string"), F.lit("")).cast("binary")), F.lit(modulus))


# --- words of many texts at once, as 64-bit hashes -----------------------------------------

_BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[32, 9, 10, 11, 12, 13]] = True
_POWERS: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse modulo 2**64, at least ``n`` of each."""
    size = 1 << max(16, int(n - 1).bit_length())
    if size not in _POWERS:
        _POWERS.clear()
        inverse = np.uint64(pow(int(_BASE), -1, 1 << 64))
        out = []
        for b in (_BASE, inverse):
            p = np.full(size, b, dtype=np.uint64)
            p[0] = 1
            out.append(np.multiply.accumulate(p))
        _POWERS[size] = (out[0], out[1])
    return _POWERS[size]


def mix(h: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit values (xor-shift and multiply rounds)."""
    h = h ^ (h >> np.uint64(30))
    h *= np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(27)
    h *= np.uint64(0x94D049BB133111EB)
    h ^= h >> np.uint64(31)
    return h


def word_spans(raw: np.ndarray, between: np.ndarray = _SPACE) -> tuple[np.ndarray, np.ndarray]:
    """Start and end of each word in a byte array; ``between`` marks the bytes that part words."""
    gap = np.ones(len(raw) + 2, dtype=bool)
    gap[1:-1] = between[raw]
    edge = np.flatnonzero(gap[1:] != gap[:-1])
    return edge[0::2], edge[1::2]


def lowered(text: bytes) -> np.ndarray:
    """The bytes with A-Z in lower case; other letters stay."""
    return _LOWER[np.frombuffer(text, dtype=np.uint8)]


#: Longest stretch of bytes hashed at once; it bounds memory for texts of any length.
STRETCH = 1 << 20


def word_hashes(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each word: a polynomial over its bytes, scrambled.

    Equal words have equal hashes wherever they stand; the sum over each word comes
    from one running sum, rebased by the inverse power at the word's start.
    """
    out = np.zeros(len(starts), dtype=np.uint64)
    at = 0
    while at < len(starts):
        origin = starts[at]
        to = max(at + 1, int(np.searchsorted(ends, origin + STRETCH, side="right")))
        if ends[at] - origin > STRETCH:
            out[at] = _long_word(raw[origin : ends[at]])
        else:
            part = raw[origin : ends[to - 1]]
            power, inverse = _powers(len(part) + 1)
            run = np.zeros(len(part) + 1, dtype=np.uint64)
            np.cumsum((part.astype(np.uint64) + np.uint64(1)) * power[: len(part)], out=run[1:])
            s, e = starts[at:to] - origin, ends[at:to] - origin
            out[at:to] = (run[e] - run[s]) * inverse[s]
        at = to
    return mix(out + (ends - starts).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))


def _long_word(raw: np.ndarray) -> np.uint64:
    total, scale = 0, 1
    for at in range(0, len(raw), STRETCH):
        part = raw[at : at + STRETCH]
        power, _ = _powers(STRETCH + 1)
        own = int(np.sum((part.astype(np.uint64) + np.uint64(1)) * power[: len(part)], dtype=np.uint64))
        total = (total + own * scale) & (1 << 64) - 1
        scale = scale * pow(int(_BASE), STRETCH, 1 << 64) & (1 << 64) - 1
    return np.uint64(total)


def joined(hashes: list[np.ndarray]) -> np.ndarray:
    """One hash for each sequence of word hashes (arrays aligned by position)."""
    h = np.full(len(hashes[0]), np.uint64(len(hashes)), dtype=np.uint64)
    for x in hashes:
        h = mix(h * np.uint64(0xFF51AFD7ED558CCD) + x)
    return h


def document_words(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """Word hashes of all texts, one after the other, and where each text begins (n + 1 offsets)."""
    parts = [(t or "").encode("utf-8", "surrogatepass") for t in texts]
    raw = lowered(b"\n".join(parts) + b"\n")
    starts, ends = word_spans(raw)
    sizes = np.fromiter((len(p) + 1 for p in parts), dtype=np.int64, count=len(parts))
    at = np.zeros(len(parts) + 1, dtype=np.int64)
    np.cumsum(sizes, out=at[1:])
    return word_hashes(raw, starts, ends), np.searchsorted(starts, at)


def blocks(batches, text: str | int = "text", limit: int = 4 << 20):
    """Split Arrow batches into runs of rows with about ``limit`` bytes of text (one row at least)."""
    for batch in batches:
        if not batch.num_rows:
            continue
        sizes = pc.fill_null(pc.binary_length(batch.column(text if isinstance(text, int) else batch.schema.get_field_index(text))), 0).to_numpy(zero_copy_only=False)
        group = np.cumsum(sizes.astype(np.int64) + 1) // limit
        cuts = np.flatnonzero(np.diff(group)) + 1
        for a, b in zip([0, *cuts], [*cuts, batch.num_rows], strict=True):
            if b > a:
                yield batch.slice(a, b - a)


def tidy(run):
    """A function for mapInArrow that gives freed memory back to the system when its task ends.

    Python workers live on from task to task; what the allocators keep for later would
    count against the executor in every stage that follows.
    """

    def tidied(batches):
        try:
            yield from run(batches)
        finally:
            release_memory()

    return tidied


def release_memory() -> None:
    import ctypes

    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc only
    if trim is not None:
        trim(0)


def settle_table(df: DataFrame, keep: bool = False) -> DataFrame:
    """Write ``df`` as Parquet to the shared folder and read it again; smaller on disk than a checkpoint.

    An open ``scratch`` block deletes it at its end, unless ``keep`` asks for more.
    """
    path = shared_dir(df.sparkSession)
    if not keep:
        delete_later(df.sparkSession, path)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def join_unique(left: DataFrame, right: DataFrame, keys: list[str], spread_by: list[str], salts: int = 16) -> DataFrame:
    """Inner join to rows that are unique by ``keys``, where one key may hold a large share of ``left``.

    The left rows of a key go to ``salts`` places by a hash of ``spread_by``; the right rows,
    far fewer, are repeated for each.
    """
    place = F.pmod(F.xxhash64(*spread_by), F.lit(salts)).cast("int")
    many = right.withColumn("__salt", F.explode(F.array(*(F.lit(s) for s in range(salts)))))
    return left.withColumn("__salt", place).join(many, [*keys, "__salt"]).drop("__salt")
