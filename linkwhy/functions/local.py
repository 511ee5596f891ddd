"""The union of one pair's explanations in one task, for pairs whose instances fit it."""

from __future__ import annotations

from collections import Counter, defaultdict
from itertools import combinations

from . import pattern as P


def monocount(bindings) -> int:
    return min((len(set(column)) for column in zip(*bindings, strict=True)), default=1)


def order(score: float, n_nodes: int, n_edges: int, key: str) -> tuple:
    """The total order of rankings: score, then fewer nodes, fewer edges, smaller key."""
    return (-score, n_nodes, n_edges, key)


def part_maps(left, right):
    """Match arrays: every non-empty one-to-one part of the relation between equal entities."""
    out = [()]
    for x in left:
        out = [m + (j,) for m in out for j in [0, *(i + 1 for i, y in enumerate(right) if y == x and i + 1 not in m)]]
    return [m for m in out if any(m)]


class Union:
    """Rounds over explanations of one pair; see ``operators.union.combine`` for the strategies.

    Paths are looked up by as many entities as a merge within the node limit must share.
    """

    def __init__(self, paths: dict[str, set[tuple]], limit: int, strategy: str, semantics: str, top: tuple[str, int] | None = None):
        self.paths, self.limit, self.strategy, self.semantics, self.top = paths, limit, strategy, semantics, top
        self.instances = {k: set(v) for k, v in paths.items()}
        self.round = dict.fromkeys(paths, 1)
        self.lineage: list[tuple[str, str, str, int]] = []
        self.work = Counter(paths=sum(map(len, paths.values())))
        self.names: dict[tuple, tuple] = {}
        self.at: dict[tuple, list[tuple[str, tuple]]] = defaultdict(list)
        self.sizes = sorted({len(b) for bindings in paths.values() for b in bindings if b})
        for key, bindings in paths.items():
            for b in bindings:
                own = sorted(set(b))
                for k in range(1, 1 + (len(own) if semantics == "simple" else min(1, len(own)))):
                    for some in combinations(own, k):
                        self.at[len(b), some].append((key, b))

    def near(self, lb: tuple) -> set[tuple[str, tuple]]:
        """The path instances that share enough entities with ``lb`` for a merge within the limit."""
        own = sorted(set(lb))
        need = lambda m: max(1, len(lb) + m + 2 - self.limit) if self.semantics == "simple" else 1
        return {pair for m in self.sizes for some in combinations(own, need(m)) for pair in self.at.get((m, some), ())}

    def name(self, left: str, right: str, match: tuple[int, ...]):
        known = self.names.get((left, right, match))
        if known is None:
            a, b = P.parse_key(left), P.parse_key(right)
            edges, n = P.merged(a, len(match) + 2, b, P.nodes_of(b), {j + 1: i + 2 for i, j in enumerate(match) if j})
            key, perm = P.canonical(edges, n)
            known = self.names[left, right, match] = (key, [v - 2 for v in perm])
        return known

    def score(self, key: str) -> tuple:
        edges = P.parse_key(key)
        n = P.nodes_of(edges)
        value = monocount(self.instances[key]) if self.top[0] == "monocount" else -n
        return order(value, n, len(edges), key)

    def run(self) -> Union:
        new, allowed, r = list(self.paths), None, 1
        while new:
            r += 1
            if self.top:
                ranked = sorted(self.instances, key=self.score)[: self.top[1]]
                new = [k for k in new if k in set(ranked)]
            made: dict[str, set] = defaultdict(set)
            born: set[tuple[str, str, str]] = set()
            for left in new:
                licensed = None if allowed is None else allowed[left]
                tried = set()
                for lb in self.instances[left]:
                    for right, rb in self.near(lb):
                        if licensed is not None and right not in licensed:
                            continue
                        tried.add(right)
                        if self.semantics == "simple":
                            maps = [tuple(rb.index(x) + 1 if x in rb else 0 for x in lb)]
                        else:
                            maps = part_maps(lb, rb)
                        for match in maps:
                            raw = lb + tuple(y for i, y in enumerate(rb) if i + 1 not in match)
                            if len(raw) + 2 > self.limit:
                                continue
                            key, perm = self.name(left, right, match)
                            if self.round.get(key, r) < r:
                                continue
                            made[key].add(tuple(raw[i] for i in perm))
                            born.add((key, left, right))
                self.work["merges_tried"] += len(tried)
            for key, bindings in made.items():
                self.instances[key], self.round[key] = bindings, r
            self.work["merges_kept"] += len(born)
            self.work["rounds"] = r
            self.lineage += [(*b, r) for b in sorted(born)]
            if self.strategy == "lineage":
                siblings: dict[str, set] = defaultdict(set)
                for _, parent, path in born:
                    siblings[parent].add(path)
                allowed = defaultdict(set)
                for child, parent, _ in born:
                    allowed[child] |= siblings[parent]
            new = list(made)
        return self
