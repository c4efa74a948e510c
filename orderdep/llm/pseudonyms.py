"""Format-preserving pseudonyms for personal data and secrets.

Values are found by pattern, validated (Luhn, octets, calendar, area codes, mod 97) and mapped by a keyed Feistel
permutation of the set of all values of their format.  The permutation is conjugated with a step of one, so no value
keeps its own form, and it depends on key and kind alone, so equal values get equal pseudonyms in all documents.

Kinds: email (local part; letters and digits each stay such), phone (national digits), card (Luhn stays valid), ip
(four octets), date (a day of 1900 to 2099 in its own notation), ssn, iban (country kept, check digits renewed),
access key, and the value of a password, token or secret.

Null and empty texts come back as they are; text around the values is not changed by a byte.
"""

from __future__ import annotations

import datetime
import hashlib
import math
import re
from collections.abc import Callable, Iterator
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql.types import ArrayType, StringType, StructField, StructType

from .common import let_go

ROUNDS = 8
_DIGITS, _LOWER, _UPPER = "0123456789", "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ"


class Feistel:
    """Keyed permutation of 0 .. a*b - 1 on pairs (a, b), and the step without fixed points built on it."""

    def __init__(self, key: bytes, kind: str, a: int, b: int, rounds: int = ROUNDS):
        self.a, self.b, self.rounds = a, b, rounds
        self.hash = hashlib.blake2b(f"{kind}|{a}|{b}".encode(), key=key[:64], digest_size=32)
        self.width = (max(a, b).bit_length() + 7) // 8 + 16

    def _f(self, r: int, half: int) -> int:
        h = self.hash.copy()
        h.update(bytes([r]) + half.to_bytes(self.width, "big"))
        out = h.digest()
        while len(out) < self.width:
            h.update(b"+")
            out += h.digest()
        return int.from_bytes(out[: self.width], "big")

    def forward(self, x: int) -> int:
        left, right = divmod(x, self.b)
        for r in range(self.rounds):
            if r % 2:
                right = (right + self._f(r, left)) % self.b
            else:
                left = (left + self._f(r, right)) % self.a
        return left * self.b + right

    def backward(self, x: int) -> int:
        left, right = divmod(x, self.b)
        for r in reversed(range(self.rounds)):
            if r % 2:
                right = (right - self._f(r, left)) % self.b
            else:
                left = (left - self._f(r, right)) % self.a
        return left * self.b + right

    def other(self, x: int) -> int:
        return self.backward((self.forward(x) + 1) % (self.a * self.b))

    def back(self, x: int) -> int:
        """Undoes other()."""
        return self.backward((self.forward(x) - 1) % (self.a * self.b))


class Permuter:
    """Permutes strings place by place within their alphabets."""

    def __init__(self, key: bytes):
        if not key:
            raise ValueError("a key is needed")
        self.key = key
        self.number = lru_cache(200_000)(self._number)
        self._feistel = lru_cache(10_000)(lambda kind, a, b: Feistel(key, kind, a, b))

    def _number(self, kind: str, x: int, radices: tuple[int, ...], back: bool = False) -> int:
        half = len(radices) // 2
        f = self._feistel(kind, math.prod(radices[:half]), math.prod(radices[half:]))
        return f.back(x) if back else f.other(x)

    def classes(self, kind: str, text: str, back: bool = False) -> str:
        """Each ASCII letter or digit becomes one of its own class; other characters stay."""
        sets = [next((s for s in (_DIGITS, _LOWER, _UPPER) if c in s), "") for c in text]
        return self.within(kind, text, sets, back)

    def within(self, kind: str, text: str, sets: list[str], back: bool = False) -> str:
        radices = tuple(len(s) for s in sets if s)
        if not radices:
            return text
        x = 0
        for c, s in zip(text, sets):
            if s:
                x = x * len(s) + s.index(c)
        x = self.number(kind, x, radices, back)
        out = list(text)
        for k in range(len(text) - 1, -1, -1):
            if sets[k]:
                x, r = divmod(x, len(sets[k]))
                out[k] = sets[k][r]
        return "".join(out)


def luhn_digit(digits: str) -> int:
    """The check digit behind these digits."""
    total = 0
    for k, c in enumerate(reversed(digits)):
        d = int(c) * (2 if k % 2 == 0 else 1)
        total += d - 9 if d > 9 else d
    return -total % 10


def _digits_only(text: str) -> str:
    return "".join(c for c in text if c in _DIGITS)


def _put_back(shape: str, digits: str) -> str:
    it = iter(digits)
    return "".join(next(it) if c in _DIGITS else c for c in shape)


def email(p: Permuter, m: re.Match, back: bool = False) -> str | None:
    return p.classes("email", m["local"], back) + m["rest"]


def phone(p: Permuter, m: re.Match, back: bool = False) -> str | None:
    lead, rest = (m["lead"], m["national"]) if m["lead"] else ("", m["local"])
    digits = _digits_only(rest)
    if not 7 <= len(digits) <= 12:
        return None
    return lead + _put_back(rest, p.classes("phone", digits, back))


def card(p: Permuter, m: re.Match, back: bool = False) -> str | None:
    digits = _digits_only(m[0])
    if not 13 <= len(digits) <= 19 or luhn_digit(digits[:-1]) != int(digits[-1]):
        return None
    new = p.classes("card", digits[:-1], back)
    return _put_back(m[0], new + str(luhn_digit(new)))


def ip(p: Permuter, m: re.Match, back: bool = False) -> str | None:
    parts = [int(x) for x in m[0].split(".")]
    if any(x > 255 for x in parts) or any(len(x) > 1 and x[0] == "0" for x in m[0].split(".")):
        return None
    x = p.number("ip", int.from_bytes(bytes(parts), "big"), (256,) * 4, back)
    return ".".join(map(str, x.to_bytes(4, "big")))


_DAY_ONE, _DAYS = datetime.date(1900, 1, 1).toordinal(), datetime.date(2100, 1, 1).toordinal() - datetime.date(1900, 1, 1).toordinal()
_ROOT = math.isqrt(_DAYS) + 1


def date(p: Permuter, m: re.Match, back: bool = False) -> str | None:
    try:
        if m["y1"]:
            order = "ymd"
            day = datetime.date(int(m["y1"]), int(m["m1"]), int(m["d1"]))
        else:
            order = "mdy" if m["sep2"] == "/" else "dmy"
            a, b = int(m["a2"]), int(m["b2"])
            day = datetime.date(int(m["y2"]), *((a, b) if order == "mdy" else (b, a)))
    except ValueError:
        return None
    x = day.toordinal() - _DAY_ONE
    if not 0 <= x < _DAYS:
        return None
    x = p.number("date", x, (_ROOT, _ROOT), back)
    while x >= _DAYS:  # walks the cycle back into the calendar
        x = p.number("date", x, (_ROOT, _ROOT), back)
    day = datetime.date.fromordinal(_DAY_ONE + x)
    sep = m["sep1"] or m["sep2"]
    parts = {"y": f"{day.year:04d}", "m": f"{day.month:02d}", "d": f"{day.day:02d}"}
    return sep.join(parts[c] for c in order)


def ssn(p: Permuter, m: re.Match, back: bool = False) -> str | None:
    def good(d: str) -> bool:
        return d[:3] not in ("000", "666") and d[0] != "9" and d[3:5] != "00" and d[5:] != "0000"

    digits = _digits_only(m[0])
    if not good(digits):
        return None
    new = p.classes("ssn", digits, back)
    while not good(new):  # walks the cycle, so it stays a permutation of the valid numbers
        new = p.classes("ssn", new, back)
    return _put_back(m[0], new)


def _iban_check(country: str, rest: str) -> str:
    return f"{98 - int(''.join(str(int(c, 36)) for c in rest + country + '00')) % 97:02d}"


def iban(p: Permuter, m: re.Match, back: bool = False) -> str | None:
    flat = m[0].replace(" ", "")
    if not 15 <= len(flat) <= 34 or int("".join(str(int(c, 36)) for c in flat[4:] + flat[:4])) % 97 != 1:
        return None
    rest = p.classes("iban" + flat[:2], flat[4:], back)
    it = iter(flat[:2] + _iban_check(flat[:2], rest) + rest)
    return "".join(c if c == " " else next(it) for c in m[0])


def access_key(p: Permuter, m: re.Match, back: bool = False) -> str | None:
    return m[0][:4] + p.within("access", m[0][4:], [_UPPER + _DIGITS] * (len(m[0]) - 4), back)


def secret(p: Permuter, m: re.Match, back: bool = False) -> str | None:
    value = m["value"]
    if not re.search(r"\d", value):
        return None
    alike = _DIGITS + "abcdef"
    sets = [alike] * len(value)
    new = p.within("secret", value, sets, back) if len(value) >= 16 and all(c in alike for c in value) else p.classes("secret", value, back)
    return m["name"] + new


#: Kinds whose pattern is only a start: a further character, characters of the shortest and the longest value, and what
#: may not stand behind a value.
RUNS: dict[str, tuple[re.Pattern, int, int, re.Pattern]] = {
    "iban": (re.compile(r" ?[A-Z0-9]"), 15, 34, re.compile(r"\w")),
    "card": (re.compile(r"[ -]?[0-9]"), 13, 19, re.compile(r"\.?\d")),
}
#: Characters of an IBAN by country; this length is tried first.
IBAN_LENGTHS = {
    length: set(countries.split())
    for length, countries in {
        15: "NO", 16: "BE", 18: "DK FI FO GL NL SD", 19: "MK SI", 20: "AT BA EE KZ LT LU XK", 21: "CH HR LI LV", 22: "BG BH CR DE GB GE IE ME RS VA",
        23: "AE IL IQ OM TL", 24: "AD CZ ES MD PK RO SA SE SK TN VG", 25: "LY PT ST", 26: "IS TR", 27: "BI DJ FR GR IT MC MR SM", 28: "AL AZ BY CY DO GT HU LB NI PL SV",
        29: "BR EG PS QA UA", 30: "JO KW MU", 31: "MT SC", 32: "LC", 33: "RU",
    }.items()
}
_TO_END = re.compile(r"[\s\S]*")


def tries(kind: str, text: str, m: re.Match) -> list[re.Match]:
    """The matches to be tried from this start: all lengths that end with a group, the longest first."""
    if kind not in RUNS:
        return [m]
    further, least, most, not_behind = RUNS[kind]
    end, n, ends = m.end(), len(m[0]), []
    while n <= most:
        if n >= least and not not_behind.match(text, end):
            ends.append((n, end))
        step = further.match(text, end)
        if not step:
            break
        end, n = step.end(), n + 1
    if kind == "iban":
        ends.sort(key=lambda x: m[0][:2] in IBAN_LENGTHS.get(x[0], ()))
    return [_TO_END.match(text, m.start(), end) for _, end in reversed(ends)]


#: Kind, sign without which a text has no such value, pattern, mapping; earlier kinds win where two overlap.
KINDS: list[tuple[str, str, re.Pattern, Callable]] = [
    ("secret", "digit", re.compile(r"(?P<name>(?i:\b(?:password|passwd|pwd|token|secret|api[_-]?key))\s*[=:]\s*[\"']?)(?P<value>[^\s\"']{6,})"), secret),
    ("access_key", "digit", re.compile(r"\b(?:AKIA|ASIA)[A-Z0-9]{16}\b"), access_key),
    ("email", "at", re.compile(r"(?<![\w.+%-])(?P<local>[\w.+%-]+)(?P<rest>@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)*\.[A-Za-z]{2,})"), email),
    ("iban", "digit", re.compile(r"\b[A-Z]{2}[0-9]{2}(?= ?[A-Z0-9])"), iban),
    ("card", "digit", re.compile(r"(?<![\d.])[0-9](?=(?:[ -]?[0-9]){12})"), card),
    ("phone", "digit", re.compile(r"(?P<lead>(?<![\w+])\+\d{1,3}[ .-]?)(?P<national>\(?\d{2,4}\)?(?:[ .-]?\d{2,4}){2,4})(?!\d)|(?<!\d)(?P<local>\(\d{3}\) ?\d{3}[.-]\d{4}|\d{3}[.-]\d{3}[.-]\d{4})(?!\d)"), phone),
    ("ssn", "digit", re.compile(r"(?<![\d-])\d{3}-\d{2}-\d{4}(?![\d-])"), ssn),
    ("ip", "digit", re.compile(r"(?<![\d.])\d{1,3}(?:\.\d{1,3}){3}(?!\.?\d)"), ip),
    ("date", "digit", re.compile(r"(?<![\d./-])(?:(?P<y1>(?:19|20)\d\d)(?P<sep1>[-/.])(?P<m1>[01]\d)(?P=sep1)(?P<d1>[0-3]\d)|(?P<a2>[0-3]\d)(?P<sep2>[-/.])(?P<b2>[0-3]\d)(?P=sep2)(?P<y2>(?:19|20)\d\d))(?![\d/-]|\.\d)"), date),
]


_DIGIT = re.compile(r"[0-9]")


def replaced(text: str, p: Permuter, back: bool = False) -> tuple[str, list[str]]:
    """The text with pseudonyms, and the kind of each in order of place."""
    has = {"digit": bool(_DIGIT.search(text)), "at": "@" in text}
    if not any(has.values()):
        return text, []
    taken: list[tuple[int, int, str, str]] = []
    for kind, sign, pattern, mapped in KINDS:
        if not has[sign]:
            continue
        at = 0
        while start := pattern.search(text, at):
            at = start.end()
            for m in tries(kind, text, start):
                if any(m.start() < b and a < m.end() for a, b, _, _ in taken):
                    continue
                new = mapped(p, m, back)
                if new is not None:
                    taken.append((m.start(), m.end(), new, kind))
                    at = m.end()
                    break
    if not taken:
        return text, []
    out, at = [], 0
    for a, b, new, _ in sorted(taken):
        out += [text[at:a], new]
        at = b
    return "".join([*out, text[at:]]), [k for *_, k in sorted(taken)]


def pseudonymise(docs: DataFrame, key: bytes, *, kinds_col: str | None = None) -> DataFrame:
    """docs with pseudonyms in ``text``; ``kinds_col`` adds the kinds found, an array<string> in order of place."""
    columns = docs.columns
    at = columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p = Permuter(key)
        for b in batches:
            new, kinds = [], []
            for t in b.column(at):
                t = t.as_py()
                n, k = replaced(t, p) if t else (t, [])
                new.append(n)
                kinds.append(k)
            cols = list(b.columns)
            cols[at] = pa.array(new, cols[at].type)
            names = list(b.schema.names)
            if kinds_col:
                cols.append(pa.array(kinds, pa.list_(pa.string())))
                names.append(kinds_col)
            yield pa.RecordBatch.from_arrays(cols, names=names)
        let_go()

    schema = docs.schema
    if kinds_col:
        schema = StructType([*schema.fields, StructField(kinds_col, ArrayType(StringType()))])
    return docs.mapInArrow(run, schema)
