"""Byte-pair merging of a public byte-level vocabulary: counting, encoding, decoding.

* ``MergeTable`` reads a ``tokenizer.json`` file (path is a parameter).
* ``count_by_heap`` counts tokens of one pre-token: a heap of adjacent pairs and a
  linked list of symbols; the lowest-rank pair is popped again and again and the
  count is the number of first symbols less the number of merges.
* ``Transducer`` encodes a stream of bytes in constant memory: a token leaves once the
  lookahead that the merge list needs has been seen behind it.
* ``TextDecoder`` turns identifiers back into text byte by byte.
"""

from __future__ import annotations

import functools
import heapq
import json

import regex

#: Fixed values of byte-level vocabularies: the pre-token pattern, and the printable
#: stand-ins of the 256 bytes (below: printable bytes stand for themselves, the others
#: for code points from 256 on).
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
PRINTABLE = ((33, 126), (161, 172), (174, 255))


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def _stand_ins() -> dict[str, int]:
    own = [b for a, z in PRINTABLE for b in range(a, z + 1)]
    rest = [b for b in range(256) if b not in set(own)]
    return {chr(b): b for b in own} | {chr(256 + i): b for i, b in enumerate(rest)}


class MergeTable:
    """Merges and vocabulary of one file; ``pair[(a, b)] == (rank, merged)`` over identifiers."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        back = _stand_ins()
        vocab = spec["model"]["vocab"]
        self.token_bytes = {i: bytes(back[c] for c in s) for s, i in vocab.items()}
        self.token_id = {b: i for i, b in self.token_bytes.items()}
        self.byte_id = [self.token_id[bytes([b])] for b in range(256)]
        self.pair: dict[tuple[int, int], tuple[int, int]] = {}
        self.made_by: dict[int, tuple[int, int, int]] = {}
        self.edges: tuple[dict, dict] = ({}, {})
        self.alone: dict[int, bool] = {}
        for rank, merge in enumerate(spec["model"]["merges"]):
            a, b = merge if isinstance(merge, list) else merge.split(" ")
            self.pair[vocab[a], vocab[b]] = (rank, vocab[a + b])
            self.made_by.setdefault(vocab[a + b], (rank, vocab[a], vocab[b]))
        self.special = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        for s, i in self.special.items():
            self.token_bytes.setdefault(i, s.encode())
        self.pattern = regex.compile(PATTERN)
        self.special_pattern = regex.compile("(" + "|".join(map(regex.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        self.lookahead = self._sufficient_lookahead()
        self.suffixes = self._suffix_tree()

    def _sufficient_lookahead(self) -> int:
        """Bytes beyond a boundary after which no further input can move it.

        Compare a text with a longer one that begins with it.  Left of the end of the shorter
        text both are merged alike until one of them merges across that end: symbols x, y at
        some rank.  From then on the symbol right of x's left edge may differ: it is x, or one
        that grew from x as its leftmost part.  So the next boundary to the left can differ only
        by a merge (z, w) of higher rank whose w begins with x, and so on leftwards.  Along such a chain ranks rise, and
        each link lies the length of its left symbol further from the end.  (Equal ranks are
        merged from the left, so they start no link.)  The heaviest chain bounds the distance of any change.
        """
        size = {i: len(b) for b, i in self.token_id.items()}
        beyond: dict[int, int] = {}  # heaviest chain of higher ranks whose right symbol begins with this one
        most = 1
        for (a, b), _ in sorted(self.pair.items(), key=lambda item: -item[1][0]):
            weight = size[a] + beyond.get(a, 0)
            most = max(most, weight)
            for symbol, _ in self._edge(b, 0):
                if beyond.get(symbol, 0) < weight:
                    beyond[symbol] = weight
        return most

    def _suffix_tree(self) -> tuple[dict[int, int], list[int]]:
        """Tokens by their bytes from the last to the first: (node * 256 + byte -> node), token of each node or -1."""
        step: dict[int, int] = {}
        token = [-1]
        for raw, i in self.token_id.items():
            node = 0
            for byte in reversed(raw):
                to = step.get(node << 8 | byte)
                if to is None:
                    to = step[node << 8 | byte] = len(token)
                    token.append(-1)
                node = to
            token[node] = i
        return step, token

    def _edge(self, token: int, side: int) -> list[tuple[int, int]]:
        """The symbols that stand at one edge of a token while it grows, last first: (symbol, rank of the merge that ends it)."""
        known = self.edges[side].get(token)
        if known is None:
            known, ends = [], 1 << 60
            while token is not None:
                known.append((token, ends))
                ends, a, b = self.made_by.get(token, (None, None, None))
                token = (a, b)[side] if a is not None else None
            self.edges[side][known[0][0]] = known
        return known

    def side_by_side(self, left: int, right: int) -> bool:
        """No merge across the boundary happens while both edge symbols stand: the two tokens stay two.

        Of equal ranks the leftmost goes first: a merge across the boundary comes before one
        of the same rank inside the right token, and after one inside the left token.
        """
        ls, rs = self._edge(left, 1), self._edge(right, 0)
        i = j = 0
        while True:
            (x, x_ends), (y, y_ends) = ls[i], rs[j]
            found = self.pair.get((x, y))
            if found and found[0] < x_ends and found[0] <= y_ends:
                return False
            x_born = ls[i + 1][1] if i + 1 < len(ls) else -1
            y_born = rs[j + 1][1] if j + 1 < len(rs) else -1
            if x_born < 0 and y_born < 0:
                return True
            if x_born >= y_born:
                i += 1
            else:
                j += 1

    def stands_alone(self, token: int) -> bool:
        known = self.alone.get(token)
        if known is None:
            known = self.alone[token] = merge_ids(self, [self.byte_id[x] for x in self.token_bytes[token]]) == [token]
        return known

    def pieces(self, text: str):
        """(special identifier or None, text) for the parts between special strings."""
        if not self.special_pattern or not any(s in text for s in self.special):
            yield None, text
            return
        for part in self.special_pattern.split(text):
            if part:
                yield self.special.get(part), part


@functools.lru_cache(maxsize=2)
def merge_table(path: str) -> MergeTable:
    return MergeTable(path)


def count_by_heap(table: MergeTable, word: bytes) -> int:
    """Number of tokens of one pre-token; no identifiers are emitted."""
    n = len(word)
    if n < 2:
        return n
    pair = table.pair
    symbol = [table.byte_id[b] for b in word]
    after = list(range(1, n + 1))
    before = list(range(-1, n - 1))
    heap = []
    for i in range(n - 1):
        found = pair.get((symbol[i], symbol[i + 1]))
        if found:
            heap.append((found[0], i, found[1]))
    heapq.heapify(heap)
    merges = 0
    while heap:
        rank, i, made = heapq.heappop(heap)
        if symbol[i] < 0:
            continue
        j = after[i]
        if j >= n or pair.get((symbol[i], symbol[j])) != (rank, made):
            continue  # a neighbour has changed since this pair was pushed
        merges += 1
        symbol[i], symbol[j] = made, -1
        k = after[i] = after[j]
        if k < n:
            before[k] = i
            found = pair.get((made, symbol[k]))
            if found:
                heapq.heappush(heap, (found[0], i, found[1]))
        h = before[i]
        if h >= 0:
            found = pair.get((symbol[h], made))
            if found:
                heapq.heappush(heap, (found[0], h, found[1]))
    return n - merges


def merge_ids(table: MergeTable, symbols: list[int]) -> list[int]:
    """Plain merging by rank; for the few symbols of two tokens side by side."""
    symbols = list(symbols)
    while len(symbols) > 1:
        best = min(((table.pair.get((a, b), (1 << 60, 0))[0], i) for i, (a, b) in enumerate(zip(symbols, symbols[1:], strict=False))))
        if best[0] == 1 << 60:
            break
        i = best[1]
        symbols[i : i + 2] = [table.pair[symbols[i], symbols[i + 1]][1]]
    return symbols


class Transducer:
    """Encodes one pre-token given in pieces of bytes, emitting tokens once they are stable.

    For every prefix of the input there is one last token: the one whose bytes end
    there and that may stand behind the last token of the prefix before it (two tokens
    may stand side by side if no merge joins their edges while they grow).  A boundary
    with ``lookahead`` bytes behind it is final, so tokens up to there leave and the buffer
    never holds more than ``most_held`` bytes.
    """

    LARGEST_CACHE = 1 << 20

    def __init__(self, table: MergeTable):
        self.table = table
        self.fits: dict[tuple[int, int], bool] = {}
        self.most_held = 4 * table.lookahead
        self.reset()

    def reset(self) -> None:
        self.buffer = bytearray()
        self.last: list[int] = [-1]  # last token of each prefix of the buffer; -1: start
        self.before = -1  # the token emitted last

    def may_follow(self, left: int, right: int) -> bool:
        key = (left, right)
        known = self.fits.get(key)
        if known is None:
            known = self.table.stands_alone(right) and (left < 0 or self.table.side_by_side(left, right))
            if len(self.fits) >= self.LARGEST_CACHE:
                self.fits.clear()
            self.fits[key] = known
        return known

    def _walk(self, raw, last: list[int], begin: int) -> None:
        """Extend ``last`` by the last token of each prefix of ``raw`` beyond ``begin`` bytes."""
        (step, token_at), fits, may_follow = self.table.suffixes, self.fits, self.may_follow
        for n in range(begin, len(raw)):
            node, at, found = 0, n, []
            while at >= 0:
                node = step.get(node << 8 | raw[at])
                if node is None:
                    break
                if token_at[node] >= 0:
                    found.append((at, token_at[node]))
                at -= 1
            for at, token in reversed(found):
                fit = fits.get((last[at], token))
                if fit if fit is not None else may_follow(last[at], token):
                    last.append(token)
                    break

    def feed(self, piece: bytes) -> list[int]:
        out: list[int] = []
        for at in range(0, len(piece), self.table.lookahead):
            begin = len(self.buffer)
            self.buffer += piece[at : at + self.table.lookahead]
            self._walk(self.buffer, self.last, begin)
            if len(self.buffer) > self.most_held - self.table.lookahead:
                out += self._emit(len(self.buffer) - self.table.lookahead)
        return out

    def finish(self) -> list[int]:
        out = self._emit(len(self.buffer))
        self.reset()
        return out

    def _emit(self, until: int) -> list[int]:
        """The tokens that end at ``until`` or before."""
        size, ids, at, cut = self.table.token_bytes, [], len(self.buffer), 0
        while at > 0:
            if at <= until:
                cut = max(cut, at)
                ids.append(self.last[at])
            at -= len(size[self.last[at]])
        ids.reverse()
        if ids:
            self.before = ids[-1]
            del self.buffer[:cut]
            self.last = [self.before, *self.last[cut + 1 :]]
        return ids

    def encode(self, word: bytes) -> list[int]:
        """All tokens of one pre-token; one that fits the buffer is walked in place."""
        if len(word) > self.most_held:
            self.reset()
            ids = self.feed(word)
            return ids + self.finish()
        whole = self.table.token_id.get(word)
        if whole is not None and self.may_follow(-1, whole):
            return [whole]
        last = [-1]
        self._walk(word, last, 0)
        ids, at, of = [], len(word), self.table.token_bytes
        while at:
            ids.append(last[at])
            at -= len(of[last[at]])
        ids.reverse()
        return ids


class TextDecoder:
    """A state machine from bytes to text: the state is an incomplete character of 0 to 3 bytes.

    Bytes that are no UTF-8 become U+FFFD, one for each longest broken prefix.
    """

    def __init__(self, table: MergeTable):
        import codecs

        self.bytes_of = table.token_bytes
        self.machine = codecs.getincrementaldecoder("utf-8")("replace")

    def feed(self, ids) -> str:
        return self.machine.decode(b"".join(map(self.bytes_of.__getitem__, ids)))

    def finish(self) -> str:
        return self.machine.decode(b"", final=True)


#: Characters of a slice of text, where it can be cut.
SLICE = 1 << 16


def slices(text: str, size: int = SLICE):
    """Parts of a text, cut only where pre-tokens end: before one space between two letters."""
    at = 0
    while len(text) - at > size:
        found = _CUT.search(text, at + size)
        if not found:
            break
        yield text[at : found.start()]
        at = found.start()
    yield text[at:]


_CUT = regex.compile(r"(?<=\p{L}) (?=\p{L})")
