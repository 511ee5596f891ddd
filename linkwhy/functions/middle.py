"""Patterns with one variable: how many entities two targets share, from packed blocks of targets.

A target's entities are those that all edges of the pattern at this target lead to.  The value of a start and
an end is the number of entities that both have, so a block of starts and a block of ends are enough to count all their pairs.
"""

from __future__ import annotations

import io

import numpy as np
import pyarrow as pa

from . import pattern as P

BLOCK = "p int, side int, block int, data binary"
VALUES = "p int, start long, value long, n_pairs long"


def sides(edges: frozenset[P.Edge]) -> list[tuple[int, str, int]] | None:
    """(target, label, way) of each edge if all edges join a target and the one variable; else None."""
    out = []
    for a, rel, b, directed in edges:
        target = b if a == 2 else a
        if {a, b} != {target, 2} or target not in (P.START, P.END):
            return None
        out.append((target, rel, 0 if not directed else 1 if b == 2 else -1))
    return sorted(out) if {t for t, _, _ in out} == {P.START, P.END} else None


def pack(key: tuple, table: pa.Table) -> pa.Table:
    """One row for a block of targets: (u, vs) of starts by start, of ends turned over, by entity."""
    p, side, block = (k.as_py() for k in key)
    own = table.column("vs").combine_chunks()
    u, vs = table.column("u").to_numpy(), own.flatten().to_numpy(zero_copy_only=False)
    lengths = np.asarray(own.value_lengths(), dtype=np.int64)
    middles, codes = np.unique(vs, return_inverse=True)
    if side == P.END:
        order = np.argsort(u)
        rank = np.empty(len(u), dtype=np.int64)
        rank[order] = np.arange(len(u))
        ends = np.repeat(rank, lengths)
        by = np.lexsort((ends, codes))
        u, lengths, codes = u[order], np.bincount(codes, minlength=len(middles)), ends[by]
    out = io.BytesIO()
    np.savez_compressed(out, u=u, middles=middles, lengths=lengths.astype(np.int32), gaps=np.diff(codes, prepend=0).astype(np.int32))
    return pa.table({"p": pa.array([p], pa.int32()), "side": pa.array([side], pa.int32()), "block": pa.array([block], pa.int32()), "data": pa.array([out.getvalue()], pa.binary())})


def _unpack(data: bytes):
    own = np.load(io.BytesIO(data))
    return own["u"], own["middles"], np.concatenate([[0], np.cumsum(own["lengths"], dtype=np.int64)]), np.cumsum(own["gaps"], dtype=np.int64)


def _numbers(counts: np.ndarray) -> np.ndarray:
    """How many of the small numbers ``counts`` are 0, 1, 2, ..."""
    top = int(counts.max())
    if top > 24:
        return np.bincount(counts)
    of = [np.count_nonzero(counts == v) for v in range(1, top + 1)]  # a few passes over bytes are faster than a look-up for each
    return np.array([len(counts) - sum(of), *of])


def count_block(starts: bytes, ends: bytes, with_self: bool):
    """For each start of a block (start, values, numbers of ends of the other block that have them)."""
    us, own, first, codes = _unpack(starts)
    es, theirs, begin, members = _unpack(ends)
    place = np.searchsorted(theirs, own)
    known = theirs[np.minimum(place, len(theirs) - 1)] == own
    same = np.searchsorted(es, us)
    is_end = es[np.minimum(same, len(es) - 1)] == us
    table = None
    if len(theirs) * len(es) <= 16 * len(members):  # no larger than twice the lists
        table = np.zeros((len(theirs), len(es)), dtype=np.uint8)
        table[np.repeat(np.arange(len(theirs)), np.diff(begin)), members] = 1
    for i, start in enumerate(us):
        mine = codes[first[i] : first[i + 1]]
        mine = place[mine[known[mine]]]
        if not len(mine):
            continue
        found = None
        if table is not None:
            numbers = np.zeros(len(es), dtype=np.uint8 if len(mine) < 256 else np.int64)
            for m in mine:
                np.add(numbers, table[m], out=numbers)
        else:
            met = np.concatenate([members[begin[m] : begin[m + 1]] for m in mine])
            if len(met) * 8 < len(es):  # few ends are met: they are sorted instead of counted among all
                found, numbers = np.unique(met, return_counts=True)
            else:
                numbers = np.bincount(met, minlength=len(es))
        if not with_self and is_end[i]:
            numbers[same[i] if found is None else found == same[i]] = 0
        of = _numbers(numbers)
        values = np.flatnonzero(of[1:]) + 1
        yield start, values, of[values]


def counter(by_start: bool, with_self: bool):
    """The function for a block of starts and one of ends: how many pairs have each value, for each start or in all."""

    def meet(key, left: pa.Table, right: pa.Table) -> pa.Table:
        columns = [[], [], []]
        total: dict[int, int] = {}
        if left.num_rows and right.num_rows:
            for start, values, numbers in count_block(left.column("starts")[0].as_py(), right.column("ends")[0].as_py(), with_self):
                if by_start:
                    for c, x in zip(columns, (np.full(len(values), start), values, numbers), strict=True):
                        c.append(x)
                else:
                    for v, n in zip(values.tolist(), numbers.tolist(), strict=True):
                        total[v] = total.get(v, 0) + n
        if by_start:
            start, values, numbers = (np.concatenate([*c, np.zeros(0, dtype=np.int64)]) for c in columns)
        else:
            start, values, numbers = [None] * len(total), list(total), list(total.values())
        p = key[0].as_py()
        return pa.table({"p": pa.array([p] * len(values), pa.int32()), "start": pa.array(start, pa.int64()), "value": pa.array(values, pa.int64()), "n_pairs": pa.array(numbers, pa.int64())})

    return meet
