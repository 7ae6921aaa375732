"""PII: format-preserving Feistel pseudonyms.

Validated numbers and dates are permuted within their format under a key: the digits of a phone or card number, the octets
of an address, the day of a date. What is permuted is the value, not its spelling, so equal values get equal pseudonyms
wherever they stand and however they are written, and documents stay linked: a date by its day, in any order of its parts
and with or without leading zeros; a phone number by its national digits under its country code, in any grouping; a card
number, account number (IBAN) or social security number by its digits, with any separators. Numbers that fail their check
(Luhn digit, IBAN check digits, octets above 255, days that do not exist, social security numbers never given out, unknown
country codes) are no such values and stay as they are. Without the key the permutation is not undone, with it
`replace_pii(back=True)` undoes it.

A value is an index into the domain of its format. A balanced Feistel network over two halves of the next even number of
bits permutes a domain of a power of four, and indices that leave the format's domain are sent through again until they
are back in it (cycle walking; fewer than four passes on average). The round function is keyed BLAKE2 with the format's
name as a tweak.
"""

from __future__ import annotations

import datetime
import hashlib
import hmac
import re

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import batch_of, map_arrow

_ROUNDS = 8
#: Dates are permuted among the days of this span.
_FIRST, _LAST = datetime.date(1900, 1, 1), datetime.date(2099, 12, 31)

# fixed values: the country calling codes of two digits
_CODES_OF_TWO = frozenset("20 27 30 31 32 33 34 36 39 40 41 43 44 45 46 47 48 49 51 52 53 54 55 56 57 58 60 61 62 63 64 65 66 81 82 84 86 90 91 92 93 94 95 98".split())

# formats, in the order in which they are tried at a place
_EMAIL = r"[A-Za-z0-9][A-Za-z0-9._%+-]{0,63}@[A-Za-z0-9-]{1,63}(?:\.[A-Za-z0-9-]{1,63}){1,8}"
_SCAN = re.compile(
    rf"(?P<email>{_EMAIL})"
    r"|(?<![\d.])(?P<ip>\d{1,3}(?:\.\d{1,3}){3})(?![\d]|\.\d)"
    r"|(?<![\w-])(?P<date>(?:19|20)\d\d(?P<d1>[-/.])\d\d(?P=d1)\d\d|\d\d?(?P<d2>[-/.])\d\d?(?P=d2)(?:19|20)\d\d)(?![\w-])"
    r"|(?<![\w-])(?P<ssn>\d{3}-\d\d-\d{4})(?![\w-])"
    r"|(?<![\w])(?P<iban>[A-Z]{2}\d\d(?:\x20?[A-Z0-9]{4}){3,7}(?:\x20?[A-Z0-9]{1,3})?)(?!\w)"
    r"|(?<!\w)(?P<card>\d{4}(?P<cs>[ -]?)\d{4}(?P=cs)\d{4}(?P=cs)\d{1,7}|\d{13,19})(?!\w)"
    r"|(?<!\w)(?P<phone>(?:\+\d{1,3}[ .-]?)?(?:\(\d{2,4}\)|\d{2,4})[ .-]\d{3,4}[ .-]\d{3,4}|\+\d{8,14})(?!\w)"
)
_MARK = re.compile(r"[0-9@]")


class Feistel:
    """Keyed permutations of ranges 0..size-1, one for each (tweak, size)."""

    def __init__(self, key: bytes):
        self.key = hashlib.blake2b(key, digest_size=32).digest()

    def _round(self, tweak: bytes, i: int, half: int, mask: int) -> int:
        data = tweak + bytes([i]) + half.to_bytes(24, "big")
        return int.from_bytes(hashlib.blake2b(data, key=self.key, digest_size=24).digest(), "big") & mask

    def _pass(self, tweak: bytes, x: int, bits: int, back: bool) -> int:
        mask = (1 << bits) - 1
        a, b = x >> bits, x & mask
        for i in reversed(range(_ROUNDS)) if back else range(_ROUNDS):
            if back:
                a, b = b ^ self._round(tweak, i, a, mask), a
            else:
                a, b = b, a ^ self._round(tweak, i, b, mask)
        return a << bits | b

    def permute(self, tweak: str, x: int, size: int, back: bool = False) -> int:
        if size <= 1:
            return x
        bits = ((size - 1).bit_length() + 1) // 2
        tag = f"{tweak}/{size}".encode()
        x = self._pass(tag, x, bits, back)
        while x >= size:
            x = self._pass(tag, x, bits, back)
        return x


def luhn_digit(digits: str) -> str:
    """The digit that makes a number valid when it follows these."""
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = int(c) * (2 if i % 2 == 0 else 1)
        total += d - 9 if d > 9 else d
    return str(-total % 10)


def _iban_check(country: str, rest: str) -> str:
    number = "".join(str(int(c, 36)) for c in rest + country + "00")
    return f"{98 - int(number) % 97:02d}"


def _ssn_ok(digits: str) -> bool:
    return digits[:3] not in ("000", "666") and digits[0] != "9" and digits[3:5] != "00" and digits[5:] != "0000"


def _day_class(day: datetime.date) -> tuple[bool, bool, bool]:
    """Whether the day of the month has two digits, is above 12, and the month has two digits."""
    return day.day > 9, day.day > 12, day.month > 9


def _country_digits(digits: str) -> int | None:
    """Number of digits of the country code that an international number begins with; all codes but those of one and two
    digits have three."""
    if digits[0] == "0":
        return None
    return 1 if digits[0] in "17" else 2 if digits[:2] in _CODES_OF_TWO else 3


def _refill(shape: str, chars: str) -> str:
    """The letters and digits of shape replaced in order."""
    left = iter(chars)
    return "".join(next(left) if c.isalnum() else c for c in shape)


def _digits(f: Feistel, tweak: str, digits: str, back: bool) -> str:
    return f"{f.permute(tweak, int(digits), 10 ** len(digits), back):0{len(digits)}d}" if digits else ""


def _mixed(f: Feistel, tweak: str, text: str, back: bool) -> str:
    """Letters and digits permuted together, each place keeping its kind; case counts as kind."""
    sets = [("0123456789" if c.isdigit() else "abcdefghijklmnopqrstuvwxyz" if c.islower() else "ABCDEFGHIJKLMNOPQRSTUVWXYZ") if c.isalnum() and c.isascii() else c for c in text]
    x, size = 0, 1
    for c, s in zip(text, sets, strict=True):
        x, size = x * len(s) + s.index(c), size * len(s)
    x = f.permute(tweak, x, size, back)
    out = []
    for s in reversed(sets):
        x, at = divmod(x, len(s))
        out.append(s[at])
    return "".join(reversed(out))


def pseudonym(f: Feistel, kind: str, value: str, back: bool = False) -> str | None:
    """The pseudonym of a value of a kind, or None if the value is not valid."""
    plain = "".join(c for c in value if c.isalnum())
    if kind == "email":
        local, _, domain = value.partition("@")
        return _mixed(f, "email", local, back) + "@" + domain
    if kind == "ip":
        octets = [int(o) for o in value.split(".")]
        if max(octets) > 255:
            return None
        x = f.permute("ip", int.from_bytes(bytes(octets), "big"), 1 << 32, back)
        return ".".join(map(str, x.to_bytes(4, "big")))
    if kind == "date":
        parts = re.split(r"[-/.]", value)
        year_first = len(parts[0]) == 4
        y, m, d = (int(p) for p in (parts if year_first else (parts[2], parts[1], parts[0])))
        month_first = not year_first and m > 12 and d <= 12
        if month_first:
            m, d = d, m
        try:
            day = datetime.date(y, m, d)
        except ValueError:
            return None
        if not _FIRST <= day <= _LAST:
            return None
        # the pseudonym is a day that any spelling writes as long as this one, and reads the same way back
        like, span, x = _day_class(day), (_LAST - _FIRST).days + 1, (day - _FIRST).days
        while True:
            x = f.permute("date", x, span, back)
            new = _FIRST + datetime.timedelta(x)
            if _day_class(new) == like:
                break
        sep = value[len(parts[0])]
        if year_first:
            return f"{new.year:04d}{sep}{new.month:02d}{sep}{new.day:02d}"
        one, two = (new.month, new.day) if month_first else (new.day, new.month)
        return f"{one:0{len(parts[0])}d}{sep}{two:0{len(parts[1])}d}{sep}{new.year:04d}"
    if kind == "ssn":
        if not _ssn_ok(plain):
            return None
        while True:
            plain = _digits(f, "ssn", plain, back)
            if _ssn_ok(plain):
                return _refill(value, plain)
    if kind == "iban":
        if not 15 <= len(plain) <= 34 or _iban_check(plain[:2], plain[4:]) != plain[2:4]:
            return None
        rest = _mixed(f, "iban" + plain[:2], plain[4:], back)
        return _refill(value, plain[:2] + _iban_check(plain[:2], rest) + rest)
    if kind == "card":
        body = plain[:-1]
        if not 13 <= len(plain) <= 19:
            return None
        if luhn_digit(body) == plain[-1]:
            new = _digits(f, "card", body, back)
            return _refill(value, new + luhn_digit(new))
        return None
    if kind == "phone":
        if not 8 <= len(plain) <= 15:
            return None
        # the country code stays
        keep = _country_digits(plain) if value.startswith("+") else 0
        if keep is None:
            return None
        return _refill(value, plain[:keep] + _digits(f, f"phone{plain[:keep]}", plain[keep:], back))
    return None


def pseudonymise(text: str, f: Feistel, back: bool = False) -> tuple[str, list[tuple[str, int, int, str]]]:
    """The text with every valid value replaced, and (kind, start, end, pseudonym) in code points of the given text. Every
    pseudonym is as long as its value, addresses aside."""
    out, spans, at, line_at = [], [], 0, 0
    for line in text.split("\n"):  # no value spans lines, and most lines hold none
        if _MARK.search(line):
            for m in _SCAN.finditer(text, line_at, line_at + len(line)):
                new = pseudonym(f, m.lastgroup, m[0], back)
                if new is not None:
                    out += [text[at : m.start()], new]
                    at = m.end()
                    spans.append((m.lastgroup, m.start(), m.end(), new))
        line_at += len(line) + 1
    return "".join([*out, text[at:]]), spans


def replace_pii(docs: DataFrame, key: bytes, id_col: str = "doc_id", text_col: str = "text", back: bool = False) -> DataFrame:
    """(doc_id, text, spans array<struct<kind,start,end,pseudonym>>) for every row of docs.

    The key never leaves the task closures and is not written anywhere. Texts without values come back as they are, null
    as null. back=True restores the values of a replaced table. An empty table gives an empty result; other columns are
    ignored.
    """
    check = hmac.new(key, b"format-preserving", hashlib.sha256).digest()

    def fn(batch: pa.RecordBatch):
        f = Feistel(check)
        texts, spans = [], []
        for t in batch.column(1).to_pylist():
            if not t or not any(c in t for c in "0123456789@"):
                texts.append(t)
                spans.append([])
                continue
            new, found = pseudonymise(t, f, back)
            texts.append(new)
            spans.append([{"kind": k, "start": s, "end": e, "pseudonym": p} for k, s, e, p in found])
        kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64()), ("pseudonym", pa.string())]))
        yield batch_of({"doc_id": batch.column(0), "text": pa.array(texts, pa.string()), "spans": pa.array(spans, kind)})

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return map_arrow(rows, fn, "doc_id long, text string, spans array<struct<kind:string,start:long,end:long,pseudonym:string>>")
