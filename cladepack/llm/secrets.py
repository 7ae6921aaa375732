"""Secret scans: base patterns, and a guess-cost estimate of values in a credential context.

The base kinds are assignments, access keys and long hexadecimal strings. Beyond them, a value that follows a credential
word in looser wording is a secret if it would take many guesses. The number of guesses is the least over all ways to cut
the value into dictionary words, dates, repeats, keyboard walks and brute-force spans, found by dynamic programming over
the end positions: cost(j) = min over i of cost(i) + log10 guesses(i..j) + a small price for one more part.
"""

from __future__ import annotations

import math
import re
from array import array

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import batch_of, map_arrow

# fixed values: the base patterns of the contract
_ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
_ACCESS = re.compile(r"AKIA[A-Z0-9]+")
_HEX = re.compile(r"[0-9a-f]{24,}")
KINDS = ("assign", "access", "hex", "guess")

#: Words that a credential's value may follow, alone or in a name (DB_PASSWORD, aws_secret_access_key, "auth-token"), how they
#: may follow each other, and what leads to the value.
_WORD = r"(?:pass(?:word|wd|phrase|code)?|pwd|secret|token|(?:api|access|private)[_ -]?key|credentials?|auth(?:orization)?|bearer)"
_LINK = r"""["']?\x20*+(?::|=>|=|\bis\b\x20*+:?)?\x20*+["'`]?"""
_CONTEXT = re.compile(rf"""(?<![A-Za-z]){_WORD}(?:[_-](?:{_WORD}|key|access|id|value))*+(?![A-Za-z])(?:{_LINK}\b(?:{_WORD}|key)\b)*+{_LINK}([^\s"'`,;<>()]+)""", re.I | re.A)
#: A password in the user part of an address.
_USER = re.compile(r"://[^\s/:@]*:([^\s/@]+)@")
_HINTS = ("pass", "pwd", "secret", "token", "key", "credential", "auth", "bearer", "://")
#: log10 of the guesses from which a value counts as a secret.
LEAST_GUESSES = 8.0

# fixed values: common words of passwords, most common first
_WORDS = """password qwerty dragon monkey letmein football baseball master shadow michael superman batman trustno login
admin welcome hello freedom whatever princess sunshine iloveyou secret flower starwars summer winter spring autumn
charlie jordan hunter ranger soccer hockey killer george thomas pepper ginger cookie cheese computer internet
access test user root guest demo default change temp pass word love money happy tiger lucky silver golden orange purple
yellow green black white blue red king queen angel star moon sun house home music game play work mail the and for you
that this with from are not have your one two three correct horse battery staple""".split()
_RANK = {w: i + 2 for i, w in enumerate(_WORDS)}
_LONGEST = max(map(len, _WORDS))
# fixed values: rows of the common keyboard, and the plain orders
_ROWS = ("qwertyuiop", "asdfghjkl", "zxcvbnm", "1234567890", "qwertzuiop", "azertyuiop", "abcdefghijklmnopqrstuvwxyz", "0123456789")
_NEXT: dict[str, set[str]] = {}
for _row in _ROWS:
    for _a, _b in zip(_row, _row[1:]):
        _NEXT.setdefault(_a, set()).add(_b)
        _NEXT.setdefault(_b, set()).add(_a)
for _up, _low in ((0, 1), (1, 2)):
    for _i, _c in enumerate(_ROWS[_low]):
        for _d in _ROWS[_up][_i : _i + 2]:
            _NEXT.setdefault(_c, set()).add(_d)
            _NEXT.setdefault(_d, set()).add(_c)
_LEET = str.maketrans("@430$5!17+", "aaeossiltt")
_PART_COST = 0.3
_TURN_COST = math.log10(2.5)
# up to this length periods are compared one by one, which is faster there
_SHORT = 256


def _class_size(text: str) -> int:
    return 26 * any(c.islower() for c in text) + 26 * any(c.isupper() for c in text) + 10 * any(c.isdigit() for c in text) + 33 * any(not c.isalnum() for c in text)


def _word_cost(text: str) -> float | None:
    low = text.lower()
    rank = _RANK.get(low)
    extra = 0.0
    if rank is None:
        rank = _RANK.get(low.translate(_LEET))
        extra = math.log10(4)
    if rank is None:
        return None
    uppers = sum(c.isupper() for c in text)
    if uppers and not (uppers == len(text) or (uppers == 1 and text[0].isupper())):
        extra += math.log10(math.comb(len(text), min(uppers, len(text) - uppers)) + 1)
    elif uppers:
        extra += math.log10(2)
    return math.log10(rank) + extra


def _date_cost(text: str) -> float | None:
    if not 4 <= len(text) <= 10:
        return None
    if re.fullmatch(r"(19|20)\d\d", text):
        return math.log10(120)
    m = re.fullmatch(r"(\d{4})([-/.]?)(\d\d)\2(\d\d)", text)
    parts = (m[1], m[3], m[4]) if m else None
    if parts is None and (m := re.fullmatch(r"(\d\d)([-/.]?)(\d\d)\2(\d{4}|\d\d)", text)):
        parts = (m[4], m[3], m[1]) if int(m[3]) <= 12 else (m[4], m[1], m[3])
    if parts is None or not (1 <= int(parts[1]) <= 12 and 1 <= int(parts[2]) <= 31):
        return None
    return math.log10(120 * 365) + (math.log10(4) if m[2] else 0)


def _repeat_price(unit: str, times: int) -> float:
    return len(unit) * math.log10(max(10, _class_size(unit))) + math.log10(times)


def _repeat_cost(text: str) -> float | None:
    n = len(text)
    for unit in range(1, n // 2 + 1):
        if n % unit == 0 and text[:unit] * (n // unit) == text:
            return _repeat_price(text[:unit], n // unit)
    return None


def _walk_price(length: int, turns: int) -> float:
    return math.log10(47) + math.log10(length) + turns * _TURN_COST


def _walk_cost(text: str) -> float | None:
    low = text.lower()
    if len(low) < 3 or any(b not in _NEXT.get(a, ()) for a, b in zip(low, low[1:])):
        return None
    return _walk_price(len(low), sum(_turns(a, b, c) for a, b, c in zip(low, low[1:], low[2:])))


def _turns(a: str, b: str, c: str) -> bool:
    return ord(b) - ord(a) != ord(c) - ord(b)


def _runs_of_short(value: str) -> dict[tuple[int, int], int]:
    n, runs = len(value), {}
    for period in range(1, n // 2 + 1):
        start = 0
        for at in range(n - period + 1):
            if at == n - period or value[at] != value[at + period]:
                if at - start >= period:
                    runs.setdefault((start, at + period), period)
                start = at + 1
    return runs


def _common(ranks: list[np.ndarray], a: np.ndarray, b: np.ndarray, back: bool) -> np.ndarray:
    """How far the text from a on (back: the text before a) equals the text from b on (before b); a < b."""
    n, out = len(ranks[0]), np.zeros(len(a), np.int64)
    for level in range(len(ranks) - 1, -1, -1):
        width, rank = 1 << level, ranks[level]
        at = np.flatnonzero(a - out >= width if back else b + out <= n - width)
        step = -out[at] - width if back else out[at]
        out[at[rank[a[at] + step] == rank[b[at] + step]]] += width
    return out


def _runs(value: str) -> dict[tuple[int, int], int]:
    """All longest stretches (start, end) of at least two periods, with their least period. A long value is not compared
    period by period: the substrings of each length 1, 2, 4... are ranked, which tells how far any two places agree, and a
    stretch of period p holds a multiple of p at which it can be asked for. Time n log(n)^2, memory 4 n log(n) bytes."""
    n, runs = len(value), {}
    if n <= _SHORT:
        return _runs_of_short(value)
    rank = np.unique(np.frombuffer(value.encode("utf-32-le", "surrogatepass"), np.uint32), return_inverse=True)[1]
    ranks, width = [rank.astype(np.int32)], 1
    while 2 * width <= n and ranks[-1].max() + 1 < len(ranks[-1]):
        rank = ranks[-1].astype(np.int64)
        ranks.append(np.unique(rank[: n - 2 * width + 1] * n + rank[width:], return_inverse=True)[1].astype(np.int32))
        width *= 2
    period = 1
    while 2 * period <= n:
        # as many periods as make some 100,000 questions
        periods = np.arange(period, min(n // 2, period + 100_000 * period // n) + 1)
        period = int(periods[-1]) + 1
        asks = (n - 1) // periods
        p = np.repeat(periods, asks)
        at = (np.arange(len(p)) - np.repeat(np.cumsum(asks) - asks, asks)) * p
        same = ranks[0][at] == ranks[0][at + p]
        at, p = at[same], p[same]
        for k in range(0, len(p), 1_000_000):
            a, q = at[k : k + 1_000_000], p[k : k + 1_000_000]
            start, end = a - _common(ranks, a, a + q, True), a + q + _common(ranks, a, a + q, False)
            found = np.flatnonzero(end - start >= 2 * q)
            for m in found[np.unique(start[found] * (n + 1) + end[found], return_index=True)[1]]:
                runs.setdefault((int(start[m]), int(end[m])), int(q[m]))
    return runs


class _Starts:
    """The starts that a part may have whose cost grows with the logarithm of its length, the best one on top. As the end
    moves on, an older start only gains on a younger one. So a start that is no better when it comes is never needed, and
    every other one is the best until a certain end, from which the one beneath it is."""

    def __init__(self):
        self.stack: list[tuple[float, int, float]] = []  # cost before the start, start, end from which the one beneath is better

    def best(self, cost: float, start: int, end: int) -> int:
        """Takes in a start and gives the best one for this end; starts and ends come in ascending order."""
        stack = self.stack
        while stack and stack[-1][2] <= end:
            stack.pop()
        if not stack or cost + math.log10(end - start) < stack[-1][0] + math.log10(end - stack[-1][1]):
            until = math.inf
            while stack:
                gap = cost - stack[-1][0]
                until = start + (start - stack[-1][1]) / math.expm1(min(gap, 300) * math.log(10)) if gap > 0 else math.inf
                if until < stack[-1][2]:
                    break
                stack.pop()
                until = math.inf
            stack.append((cost, start, until))
        return stack[-1][1]


def guess_cost(value: str) -> tuple[float, list[tuple[str, int, int]]]:
    """log10 of the guesses that the value takes, and the cheapest cut (part, start, end): the least over all cuts, with
    parts of any length. Words and dates are no longer than the longest of their kind. Of repeats and walks, of which a
    value can have as many as pairs of positions, only those are tried that can be the cheapest for their end: walks by
    one stack of starts for each stretch of neighbouring keys, repeats by one for each stretch of a period and remainder.
    Time n log(n)^2 for n characters. A cut that ends in a brute-force span is kept beside the best other one, since more
    characters of that span cost no new part."""
    n = len(value)
    per_char = math.log10(max(10, _class_size(value)))
    costs, starts, names = array("d", [0.0]), array("q", [0]), [""]
    known, brute, begun = 0.0, math.inf, 0
    low = [c.lower() for c in value]
    turns, walk, walk_starts = array("q", [0]), 0, _Starts()
    opening: dict[int, list[tuple[int, int, int]]] = {}
    for (start, end), period in _runs(value).items():
        opening.setdefault(start + 2 * period, []).append((start, end, period))
    running: list[tuple[int, int, float, dict[int, _Starts] | None]] = []

    def before(i: int) -> float:
        return costs[i] + _PART_COST * (i > 0)

    for j in range(1, n + 1):
        # one more brute-force character
        if known + _PART_COST * (j > 1) < brute:
            brute, begun = known + _PART_COST * (j > 1), j - 1
        brute += per_char
        ways = [(before(i) + cost, i, "word") for i in range(max(0, j - _LONGEST), j) if (cost := _word_cost(value[i:j])) is not None]
        if value[j - 1].isdigit():
            ways += [(before(i) + cost, i, "date") for i in range(max(0, j - 10), j - 3) if (cost := _date_cost(value[i:j])) is not None]
        if j > 1:
            if low[j - 1] not in _NEXT.get(low[j - 2], ()):
                walk, walk_starts = j - 1, _Starts()
            turns.append(turns[-1] + (j - walk > 2 and _turns(*low[j - 3 : j])))
        if j - walk > 2:
            i = walk_starts.best(before(j - 3) - turns[j - 2] * _TURN_COST, j - 3, j)
            ways.append((before(i) + _walk_price(j - i, turns[j - 1] - turns[i + 1]), i, "walk"))
        running = [run for run in running if run[0] >= j]
        for start, end, period in opening.pop(j, ()):
            # below three periods there is but one start for an end
            running.append((end, period, _repeat_price(value[start : start + period], 1), {} if end - start >= 3 * period else None))
        for _, period, unit, by_rest in running:
            i = j - 2 * period
            if by_rest is not None:
                i = by_rest.setdefault(j % period, _Starts()).best(before(i), i, j)
            ways.append((before(i) + unit + math.log10((j - i) // period), i, "repeat"))
        known, start, name = min(ways, default=(math.inf, 0, ""))
        costs.append(min(known, brute))
        starts.append(start if known <= brute else begun)
        names.append(name if known <= brute else "brute")
    parts, j = [], n
    while j:
        parts.append((names[j], starts[j], j))
        j = starts[j]
    return costs[n], parts[::-1]


def find_secrets(text: str) -> list[tuple[str, int, int]]:
    """All spans (kind, start, end) of a text, in code points, by start and then kind. Base spans of a kind are leftmost
    and do not overlap; a guess span never overlaps a base span."""
    low = text.lower()
    hinted = any(h in low for h in _HINTS)
    spans = []
    if hinted:
        spans += [("assign", m.start(), m.end()) for m in _ASSIGN.finditer(text) if len(m[2]) >= 6]
    if "AKIA" in text:
        spans += [("access", m.start(), m.end()) for m in _ACCESS.finditer(text) if m.end() - m.start() >= 20]
    spans += [("hex", m.start(), m.end()) for m in _HEX.finditer(text)]
    if hinted:
        spans += [("guess", m.start(1), m.end(1)) for m in _USER.finditer(text) if guess_cost(m[1])[0] >= LEAST_GUESSES and not any(s < m.end(1) and m.start(1) < e for _, s, e in spans)]
        base = list(spans)
        at = 0
        while m := _CONTEXT.search(text, at):
            value = m[1].rstrip(".!?:")
            start, end = m.start(1), m.start(1) + len(value)
            if any(s < end and start < e for _, s, e in base) or guess_cost(value)[0] < LEAST_GUESSES:
                # the value may itself be the context of another
                at = start
                continue
            spans.append(("guess", start, end))
            at = m.end()
    return sorted(spans, key=lambda s: (s[1], KINDS.index(s[0]), s[2]))


def scan_secrets(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, spans array<struct<kind,start,end,log10_guesses>>) for every row of docs; whole texts, in code points.
    Null and empty texts have no spans. log10_guesses is given for assign and guess spans. An empty table gives an empty
    result; other columns are ignored."""

    def fn(batch: pa.RecordBatch):
        out = []
        for t in batch.column(1).to_pylist():
            row = []
            for kind, s, e in find_secrets(t or ""):
                value = t[s:e]
                if kind == "assign":
                    value = _ASSIGN.match(value)[2]
                row.append({"kind": kind, "start": s, "end": e, "log10_guesses": guess_cost(value)[0] if kind in ("assign", "guess") else None})
            out.append(row)
        kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64()), ("log10_guesses", pa.float64())]))
        yield batch_of({"doc_id": batch.column(0), "spans": pa.array(out, kind)})

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return map_arrow(rows, fn, "doc_id long, spans array<struct<kind:string,start:long,end:long,log10_guesses:double>>")
