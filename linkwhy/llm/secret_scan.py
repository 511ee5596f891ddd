"""Operator 10: secret scans with a guess-cost dynamic program over credential values."""

from __future__ import annotations

import functools
import hashlib
import math
import re
from collections import deque

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import settle_table

#: The three base patterns (kind, pattern, group whose length counts, least length).
BASE = (
    ("assign", re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A), 2, 8),
    ("access", re.compile(r"AKIA[A-Z0-9]+"), 0, 16),
    ("hex", re.compile(r"[0-9a-f]+"), 0, 32),
)
#: A value in a credential context, with more names, separators and characters than the base pattern has.
CONTEXT = re.compile(r"""(?<![A-Za-z])(?:pass(?:word|wd|phrase|code)?|pwd|secret|token|credentials?|(?:api|access|private|auth)[_\-\x20]?key|login|pin)["']?\x20{0,3}(?:[:=]|=>|:=|\x20is\x20)\x20{0,3}["'`]?([^\s"'`<>,;]+)""", re.I | re.A)
#: Parts of every context, to pass over texts that have none.
HINTS = ("pass", "pwd", "secret", "token", "credential", "key", "login", "pin")
KINDS = ("assign", "access", "hex", "guess")
#: Guesses (as a power of ten) from which a value counts as a secret rather than a placeholder, and least length.
LEAST_COST, LEAST_LENGTH = 8.0, 6
#: Words of the corpus that a guesser tries, most frequent first, so many; the driver and the workers hold them.
CORPUS_WORDS = 50_000

#: Common words of passwords and placeholders, most common first (fixed list).
WORDS = (
    "password pass the admin love user test qwerty letmein welcome monkey dragon master secret hello login abc "
    "football baseball sunshine princess shadow superman batman trustno flower iloveyou michael jordan access "
    "example sample change changeme default root guest token none null true false your my here value key api "
    "string text name mail server local host data base dev prod stage demo temp temporary summer winter spring "
    "autumn monday friday january april june july august october december london paris berlin madrid new old "
    "big red blue green black white cat dog home house work office company team world computer internet "
    "freedom star king queen happy lucky magic soccer hockey tiger killer pepper ginger cookie orange apple "
    "banana cheese money family friend angel baby mother father john david robert anna maria daniel thomas "
    "hunter ranger buster harley cowboy eagle thunder matrix corvette mustang phoenix yankee"
).split()
#: Usual stand-ins of letters (fixed values).
_LEET = str.maketrans({"4": "a", "@": "a", "3": "e", "1": "i", "!": "i", "0": "o", "$": "s", "5": "s", "7": "t"})
#: Rows of a keyboard, each half a key further right than the one above, and its symbols with shift (fixed values).
ROWS = ("`1234567890-=", " qwertyuiop[]", " asdfghjkl;'", " zxcvbnm,./")
SHIFTED = str.maketrans("~!@#$%^&*()_+{}:\"<>?", "`1234567890-=[];',./")
#: Costs (log10): a brute-force character, the choice of a kind of pattern, a doubling of a length, a capital, a stand-in.
BRUTE, CHOICE, DOUBLING, CASE, STAND_IN = 1.0, 0.3, math.log10(2), math.log10(2), 0.6
PERIODS = (1, 2, 3, 4)
_YEAR, _DATE = re.compile(r"(?:19|20)\d\d", re.A), re.compile(
    r"(?:19|20)\d\d([-/._]?)(?:0?[1-9]|1[0-2])\1(?:0?[1-9]|[12]\d|3[01])|(?:0?[1-9]|[12]\d|3[01])([-/._]?)(?:0?[1-9]|1[0-2])\2(?:19|20)?\d\d", re.A
)
DATE_SIZES = range(4, 11)


def _board() -> dict[tuple[str, str], tuple[int, int]]:
    """Direction of each step between neighbouring keys."""
    at = {c: (r, i) for r, row in enumerate(ROWS) for i, c in enumerate(row) if c != " "}
    around = {(0, 1), (0, -1), (1, 0), (1, -1), (-1, 0), (-1, 1)}
    return {(a, b): d for a, (r, i) in at.items() for b, (s, j) in at.items() for d in [(s - r, j - i)] if d in around}


_KEYS = _board()
_TURN = 0.5 * math.log10(len(_KEYS) / sum(len(r.strip()) for r in ROWS))  # half of the neighbours of a key, on average


def key_step(a: str, b: str) -> tuple[int, int] | None:
    return _KEYS.get((a.lower().translate(SHIFTED), b.lower().translate(SHIFTED)))


def letter_step(a: str, b: str) -> int | None:
    a, b = a.lower(), b.lower()
    return ord(b) - ord(a) if "a" <= a <= "z" and "a" <= b <= "z" and abs(ord(b) - ord(a)) == 1 else None


#: Walks: over a keyboard, and along the alphabet.  (step between two characters, log10 of the starts)
WALKS = ((key_step, math.log10(47)), (letter_step, math.log10(26)))


def word_cost(part: str, ranks: dict[str, int]) -> float | None:
    """Cost of a known word, also turned round, with capitals or with stand-ins; None for other parts."""
    low = part.lower()
    least = None
    for text, more in ((low, 0.0), (low.translate(_LEET), STAND_IN)):
        if more and text == low:
            continue
        for own, turned in ((text, 0.0), (text[::-1], math.log10(2))):
            rank = ranks.get(own)
            if rank is not None:
                upper = sum(c.isupper() for c in part)
                case = 0.0 if not upper else CASE if upper in (1, len(part)) else CASE * min(upper, len(part) - upper) + CHOICE
                cost = math.log10(rank + 1) + turned + case + more
                least = cost if least is None else min(least, cost)
    return least


def date_cost(part: str) -> float | None:
    if _YEAR.fullmatch(part):
        return math.log10(119)
    found = _DATE.fullmatch(part)
    return None if not found else math.log10(365 * 119) + (STAND_IN if found[1] or found[2] else 0.0)


class _Starts:
    """The cheapest start of a segment that ends here, inside a run of which every part is a segment.

    Its cost is that up to the start plus a doubling for each bit of its length; for each
    number of bits a queue keeps the starts that may still win.
    """

    def __init__(self, least: int):
        self.least, self.queues = least, []

    def best(self, end: int, begin: int, key) -> tuple[float, int]:
        found, low, k = (math.inf, -1), self.least, 0
        while end - low >= begin:
            high = (1 << low.bit_length()) - 1
            if k == len(self.queues):
                self.queues.append(deque())
            queue, start = self.queues[k], end - low
            value = key(start)
            while queue and queue[-1][0] >= value:
                queue.pop()
            queue.append((value, start))
            while queue[0][1] < max(begin, end - high):
                queue.popleft()
            found = min(found, (queue[0][0] + DOUBLING * low.bit_length(), queue[0][1]))
            low, k = high + 1, k + 1
        return found


@functools.lru_cache(maxsize=4)
def _known(words: tuple[str, ...]) -> tuple[dict[str, int], int]:
    ranks: dict[str, int] = {}
    for own in (WORDS, words):
        for i, w in enumerate(own):
            ranks[w] = min(ranks.get(w, i + 1), i + 1)
    return ranks, max(map(len, ranks))


def guess_cost(value: str, words: tuple[str, ...] = ()) -> tuple[float, list[tuple[int, int, str]]]:
    """Least log10 number of guesses over all segmentations of a value, and that segmentation.

    Segments: brute-force characters (ten guesses each); known words of three letters or
    more (``WORDS`` and ``words``, by rank); dates and years; repeats of one to four characters; walks
    of three keys or more.  Repeats and walks cost a doubling for each bit of their length, walks also
    for turns.  Every end of every pattern is considered; time grows as n log n.
    """
    ranks, longest = _known(words)
    n = len(value)
    best, back = [0.0] + [math.inf] * n, [(0, "")] * (n + 1)
    repeats = [(p, _Starts(max(2 * p, 3)), [0]) for p in PERIODS]
    walks = [(step, starts, _Starts(3), [0], [0] * (n + 1), [None]) for step, starts in WALKS]
    for j in range(1, n + 1):
        found = (best[j - 1] + BRUTE, j - 1, "brute")
        for i in range(max(0, j - longest), j - 2):
            cost = word_cost(value[i:j], ranks)
            if cost is not None:
                found = min(found, (best[i] + cost + CHOICE, i, "word"))
        if value[j - 1].isdigit():
            for size in DATE_SIZES:
                if size <= j and (cost := date_cost(value[j - size : j])) is not None:
                    found = min(found, (best[j - size] + cost + CHOICE, j - size, "date"))
        for p, starts, run in repeats:
            if j > p and value[j - 1] != value[j - 1 - p]:
                run[0] = j - p
                starts.queues.clear()
            cost, i = starts.best(j, run[0], best.__getitem__)
            found = min(found, (cost + p * BRUTE + CHOICE, i, "repeat"))
        for step, first, starts, run, turns, way in walks:
            if j > 1:
                now = step(value[j - 2], value[j - 1])
                turns[j - 1] = turns[j - 2] + (way[0] is not None and now != way[0])
                way[0] = now
                if now is None:
                    run[0] = j - 1
                    starts.queues.clear()
            cost, i = starts.best(j, run[0], lambda k: best[k] - _TURN * turns[k + 1])
            found = min(found, (cost + first + _TURN * (1 + turns[j - 1]) + CHOICE, i, "walk"))
        best[j], back[j] = found[0], found[1:]
    parts, at = [], n
    while at:
        i, kind = back[at]
        if parts and kind == "brute" and parts[-1][2] == "brute":
            parts[-1] = (i, parts[-1][1], "brute")
        else:
            parts.append((i, at, kind))
        at = i
    return best[n], parts[::-1]


def ranked_words(docs: DataFrame, text_col: str = "text", most: int = CORPUS_WORDS) -> tuple[str, ...]:
    """The most frequent words of 3 to 24 letters of a corpus, counted over all texts (ties by the word).

    Words from the least count on of which at most ``most`` have as many; only those come to the driver.
    """
    word = F.explode(F.split(F.lower(F.col(text_col)), r"[^\p{L}]+"))
    counts = docs.select(word.alias("w")).filter(F.length("w").between(3, 24)).groupBy("w").agg(F.count(F.lit(1)).alias("n")).filter("n > 1")
    counts = settle_table(counts)
    # different counts are few: they add up to no more than the tokens
    upto = counts.groupBy("n").agg(F.count(F.lit(1)).alias("c")).withColumn("upto", F.sum("c").over(Window.orderBy(F.desc("n"))))
    least = upto.filter(F.col("upto") <= most).agg(F.min("n")).first()[0]
    if least is None:
        return ()
    rows = counts.filter(F.col("n") >= least).collect()
    return tuple(r["w"] for r in sorted(rows, key=lambda r: (-r["n"], r["w"])))


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, end, kind number) of the base patterns; failing matches are dropped after matching."""
    out = []
    for k, (_, pattern, group, least) in enumerate(BASE):
        if k == 1 and "AKIA" not in text:
            continue
        for m in pattern.finditer(text):
            if m.end(group) - m.start(group) >= least:
                out.append((m.start(), m.end(), k))
    return out


def scan(text: str, least_cost: float = LEAST_COST, words: tuple[str, ...] = ()) -> tuple[list[tuple[int, int, int]], list[tuple[int, int, int]], float]:
    """Base spans, all spans, and the largest guess cost of a credential value in the text."""
    if not text:
        return [], [], 0.0
    low = text.lower()
    hinted = any(h in low for h in HINTS)
    if hinted:
        base = base_spans(text)
    else:
        base = [(m.start(), m.end(), 1) for m in BASE[1][1].finditer(text) if m.end() - m.start() >= 16] if "AKIA" in text else []
        base += [(m.start(), m.end(), 2) for m in _HEX.finditer(text)]
    base.sort(key=lambda s: (s[0], s[2], s[1]))
    added, most, reach, k = [], 0.0, -1, 0
    if hinted:
        for m in CONTEXT.finditer(text):
            value = m[1].rstrip(".:)]}")
            if len(value) < LEAST_LENGTH:
                continue
            cost, _ = guess_cost(value, words)
            most = max(most, cost)
            start, end = m.start(1), m.start(1) + len(value)
            while k < len(base) and base[k][0] <= start:  # the furthest end of the base spans that begin before
                reach = max(reach, base[k][1])
                k += 1
            if cost >= least_cost and reach < end:
                added.append((start, end, 3))
    return base, sorted(base + added, key=lambda s: (s[0], s[2], s[1])), most


_HEX = re.compile(r"[0-9a-f]{32,}")


def named(spans) -> str:
    return ",".join(f"{KINDS[k]}:{s}:{e}" for s, e, k in spans)


def scan_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", least_cost: float = LEAST_COST, words: tuple[str, ...] | None = None) -> DataFrame:
    """Secrets of every whole text: id, n_assign, n_access, n_hex, n_guess, base_sha256, spans, max_cost.

    Spans are ``kind:start:end`` in code points.  The three base kinds always stay; ``guess``
    adds values in a credential context whose cheapest segmentation into words, dates,
    repeats, keyboard walks and brute-force stretches needs at least 10**least_cost guesses.
    ``words``: words that a guesser tries, best first; None counts them over all texts (one pass, of which
    ``CORPUS_WORDS`` come to the driver).  Null and empty texts have no spans (base_sha256 is that of the empty string).
    Repeated rows each give a row; an empty table gives none.  The scan itself has no shuffle.
    """
    words = ranked_words(docs, text_col) if words is None else tuple(words)
    base = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    fields = "n_assign long, n_access long, n_hex long, n_guess long, base_sha256 string, spans string, max_cost double"

    def run(batches):
        import pyarrow as pa

        kinds = [pa.int64()] * 4 + [pa.string(), pa.string(), pa.float64()]
        names = [f.split()[0] for f in fields.split(", ")]
        for batch in batches:
            rows = []
            for t in batch.column(1):
                own, every, cost = scan(t.as_py() or "", least_cost, words)
                count = [sum(k == x for _, _, x in every) for k in range(4)]
                rows.append((*count, hashlib.sha256(named(own).encode()).hexdigest(), named(every), cost))
            columns = list(zip(*rows, strict=True)) if rows else [[]] * len(names)
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, k) for c, k in zip(columns, kinds, strict=True))], names=["id", *names])

    out = base.mapInArrow(run, f"id {base.schema['id'].dataType.simpleString()}, {fields}")
    return out.withColumnRenamed("id", id_col)
