"""Format-preserving pseudonyms for personal data by a keyed Feistel network.

Validated values are mapped inside their own format by a keyed bijection, so equal values stay linked across documents and
no two values of a format collide. A bijection ``E`` alone may leave a value as it is; ``E^-1(E(x) + 1)`` is a bijection too and
never does.

Formats: payment cards (13 to 19 digits in any grouping by single spaces or hyphens, alone or among other numbers, Luhn checked; the check
digit is made anew; of valid stretches that overlap the first is taken, those in the usual grouping before others), dates (ISO, also
before a time, and day and month with ``/`` or ``.``, checked on the calendar; the pseudonym is a date of 1900-2099 in the same notation; a
date that is none day first is read month first, and its pseudonym is of that sort again), social security numbers (3-2-4,
valid areas), IPv4 addresses, phone numbers (with country code or area
brackets; of at most 15 digits, or as many as the country's plan fixes: what follows is no part of them), e-mail local parts, and hexadecimal secrets
after a naming word. Digits that validate as none of these are left alone.

Defined results: null stays null, empty stays empty; documents without such values come back unchanged; whole texts are read;
repeated rows repeat; an empty table gives no rows; other columns are carried along.
"""

from __future__ import annotations

import datetime as dt
import hashlib
import hmac
import re
import warnings
from bisect import bisect_left
from functools import cache, lru_cache
from math import isqrt, prod

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

from evenpick.llm.textbits import bounded_slices, mapped, without
from evenpick.plans.durable import ship_package

ROUNDS = 10
#: Session setting that holds the key.
KEY_SETTING = "spark.evenpick.pseudonym.key"
KINDS = ("card", "date", "ssn", "ip", "phone", "email", "secret")


class Feistel:
    """Keyed bijection on 0..n-1: an alternating network over a near-square grid that holds n, walked until inside n."""

    def __init__(self, key: bytes, tweak: str, n: int):
        self.n, self.a = n, max(2, isqrt(n - 1) + 1)
        self.b = max(2, -(-n // self.a))
        self.key = hmac.new(key, f"{tweak}:{n}".encode(), hashlib.sha256).digest()

    def _round(self, i: int, x: int, m: int) -> int:
        data = i.to_bytes(1, "big") + x.to_bytes(24, "big")
        return int.from_bytes(hashlib.blake2b(data, key=self.key, digest_size=32).digest(), "big") % m

    def _once(self, x: int, back: bool) -> int:
        left, right = divmod(x, self.b)
        for i in reversed(range(ROUNDS)) if back else range(ROUNDS):
            if i % 2:
                right = (right + (-1 if back else 1) * self._round(i, left, self.b)) % self.b
            else:
                left = (left + (-1 if back else 1) * self._round(i, right, self.a)) % self.a
        return left * self.b + right

    def _walk(self, x: int, back: bool) -> int:
        x = self._once(x, back)
        while x >= self.n:
            x = self._once(x, back)
        return x

    def encrypt(self, x: int) -> int:
        return self._walk(x, False)

    def decrypt(self, x: int) -> int:
        return self._walk(x, True)

    def shift(self, x: int, by: int = 1) -> int:
        """The pseudonym of x (``by=1``) or the value behind a pseudonym (``by=-1``); never x itself if n > 1."""
        return x if self.n < 2 else self.decrypt((self.encrypt(x) + by) % self.n)


def luhn_digit(body: str) -> str:
    total = 0
    for i, c in enumerate(reversed(body)):
        d = int(c)
        total += (2 * d - 9 if d > 4 else 2 * d) if i % 2 == 0 else d
    return str(-total % 10)


def _spell(value: str, digits: str) -> str:
    """``value`` with its digits replaced in order."""
    fresh = iter(digits)
    return "".join(next(fresh) if c.isdigit() else c for c in value)


#: Alphabets inside which single characters of e-mail names and secrets move (fixed values).
ALPHABETS = ("0123456789", "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "àáâãäåæçèéêëìíîïðñòóôõöøùúûüýþÿß", "ÀÁÂÃÄÅÆÇÈÉÊËÌÍÎÏÐÑÒÓÔÕÖØÙÚÛÜÝÞ")
HEX = ("0123456789abcdef", "0123456789ABCDEF")
_DATE_FORMS = ((re.compile(r"(\d{4})-(\d\d)-(\d\d)"), "ymd"), (re.compile(r"(\d\d)([/.])(\d\d)\2(\d{4})"), "dmy"))
_EPOCH, _DAYS = dt.date(1900, 1, 1).toordinal(), dt.date(2100, 1, 1).toordinal() - dt.date(1900, 1, 1).toordinal()
#: Digits behind the country code where a numbering plan fixes them (ITU-T E.164), and most digits of a number with its country code.
NATIONAL, PHONE_DIGITS = {"1": 10, "7": 10, "33": 9, "34": 9, "44": 10, "91": 10}, 15


@cache
def _late_days() -> list[int]:
    """Days since the epoch whose day of the month is over 12: written month first, they are no dates day first."""
    return [i for i in range(_DAYS) if dt.date.fromordinal(_EPOCH + i).day > 12]


#: Candidate values that start with a digit, "+" or "(".
NUMERIC = re.compile(
    r"(?<![\w.+-])(?:(?P<stamp>\d{4}-\d\d-\d\d)(?=[Tt]\d\d)|(?:"
    r"(?P<date>\d{4}-\d\d-\d\d|\d\d[/.]\d\d[/.]\d{4})"
    r"|(?P<ip>\d{1,3}(?:\.\d{1,3}){3})"
    r"|(?P<ssn>\d{3}-\d\d-\d{4})"
    r"|(?P<phone>\+\d{1,3}[ .-]?(?:\(\d{1,4}\)[ .-]?)?\d{2,4}(?:[ .-]\d{2,4}){1,4}|\(\d{3}\) ?\d{3}[ .-]\d{4}|\d{3}-\d{3}-\d{4})"
    r")(?![\w-]|[.]\d))"
)
#: Whole runs of digit groups, in which cards are looked for, and how cards are usually grouped.
RUN = re.compile(r"(?<![\w.+-])\d(?:[ -]?\d){12,}(?![\w-]|[.]\d)")
USUAL = re.compile(r"\d{13,19}|\d{4}([ -])\d{4}\1\d{4}\1\d{1,4}(?:\1\d{1,3})?|\d{4}([ -])\d{6}\2\d{4,5}")
EMAIL = re.compile(r"([\w.%+'-]+)@([A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+)")
SECRET = re.compile(r"(?i)(\b(?:token|secret|password|passwd|api[_-]?key|access[_-]?key|key)\b\s*[=:]\s*[\"']?)([0-9a-f]{24,})(?![0-9a-z])")
_HINT = re.compile(r"[0-9@]")


class Pseudonyms:
    """All formats under one key. ``by=-1`` restores."""

    def __init__(self, key: bytes, kinds: tuple[str, ...] = KINDS, by: int = 1):
        self.key, self.kinds, self.by = key, frozenset(kinds), by
        self.net = lru_cache(4096)(lambda tweak, n: Feistel(key, tweak, n))

    def _digits(self, tweak: str, digits: str) -> str:
        return str(self.net(tweak, 10 ** len(digits)).shift(int(digits), self.by)).zfill(len(digits))

    def _letters(self, tweak: str, text: str, alphabets) -> str:
        """Mixed radix over the characters that have an alphabet; all others stay."""
        homes = [next((a for a in alphabets if c in a), "") for c in text]
        n = prod(len(h) for h in homes if h)
        x = 0
        for c, h in zip(text, homes):
            if h:
                x = x * len(h) + h.index(c)
        x, out = self.net(tweak + "/" + "".join(h[:1] or "." for h in homes), n).shift(x, self.by), []
        for c, h in zip(reversed(text), reversed(homes)):
            if h:
                x, d = divmod(x, len(h))
                c = h[d]
            out.append(c)
        return "".join(reversed(out))

    def card(self, v: str) -> str | None:
        d = re.sub(r"\D", "", v)
        if not (13 <= len(d) <= 19 and luhn_digit(d[:-1]) == d[-1] and len(set(d)) > 1):
            return None
        body = self._digits("card", d[:-1])
        return _spell(v, body + luhn_digit(body))

    def cards(self, text: str, start: int, end: int, usual: bool) -> list[tuple[int, int, str, str]]:
        """Cards in the runs of a part of a text: from the left, the longest stretch of whole groups that validates, then on behind it.

        With ``usual``, only stretches grouped as cards are, which no hyphen ties to a neighbour.
        """
        out = []
        for run in RUN.finditer(text, start, end):
            whole, i = run[0], 0
            groups = [m.span() for m in re.finditer(r"\d+", whole)]
            while i < len(groups):
                a, size, stops = groups[i][0], 0, []
                for j in range(i, len(groups)):
                    size += groups[j][1] - groups[j][0]
                    if size > 19:
                        break
                    if size >= 13:
                        stops.append((j, groups[j][1]))
                for j, b in reversed(stops):
                    v, tied = whole[a:b], "-" in (whole[a - 1 : a], whole[b : b + 1])
                    if (not usual or not tied and USUAL.fullmatch(v)) and (new := self.card(v)) is not None:
                        out.append((run.start() + a, run.start() + b, "card", new))
                        i = j
                        break
                i += 1
        return out

    def date(self, v: str) -> str | None:
        for form, order in _DATE_FORMS:
            if m := form.fullmatch(v):
                y, mo, d = (int(x) for x in ((m[1], m[2], m[3]) if order == "ymd" else (m[4], m[3], m[1])))
                late = order == "dmy" and mo > 12 >= d
                try:
                    day = dt.date(y, d if late else mo, mo if late else d).toordinal() - _EPOCH
                except ValueError:
                    return None
                if not 0 <= day < _DAYS:
                    return None
                if late:
                    days = _late_days()
                    new = dt.date.fromordinal(_EPOCH + days[self.net("late", len(days)).shift(bisect_left(days, day), self.by)])
                    return f"{new.month:02d}{m[2]}{new.day:02d}{m[2]}{new.year:04d}"
                new = dt.date.fromordinal(_EPOCH + self.net("date", _DAYS).shift(day, self.by))
                return new.isoformat() if order == "ymd" else f"{new.day:02d}{m[2]}{new.month:02d}{m[2]}{new.year:04d}"
        return None

    def ssn(self, v: str) -> str | None:
        a, g, s = (int(x) for x in v.split("-"))
        if not (0 < a < 900 and a != 666 and g and s):
            return None
        areas = 898
        x = ((a - 1 - (a > 666)) * 99 + g - 1) * 9999 + s - 1
        x, s = divmod(self.net("ssn", areas * 99 * 9999).shift(x, self.by), 9999)
        a, g = divmod(x, 99)
        return f"{a + 1 + (a >= 665):03d}-{g + 1:02d}-{s + 1:04d}"

    def ip(self, v: str) -> str | None:
        parts = v.split(".")
        if any(int(p) > 255 or (len(p) > 1 and p[0] == "0") for p in parts):
            return None
        x = self.net("ip", 1 << 32).shift(sum(int(p) << 8 * (3 - i) for i, p in enumerate(parts)), self.by)
        return ".".join(str(x >> 8 * i & 255) for i in (3, 2, 1, 0))

    def phone_end(self, text: str, start: int, end: int) -> int:
        """Where a number ends whose form may take in groups behind it.

        Behind a group that a space follows: as soon as it has the digits of its country's plan, or a value of another kind comes next;
        else behind the last group up to which it has 6 to 14 digits (``PHONE_DIGITS`` with the country code).
        """
        v = text[start:end]
        head = re.match(r"\+\d{1,3}(?!\d)|", v)[0]
        code, digits, last = head[1:], 0, end
        for g in re.finditer(r"\d+", v[len(head) :]):
            digits += len(g[0])
            at = start + len(head) + g.end()
            if digits > min(14, PHONE_DIGITS - len(code)):
                break
            if digits < 6:
                continue
            last = at
            if text[at : at + 1] == " ":
                n = NUMERIC.match(text, at + 1)
                if digits == NATIONAL.get(code) or n and n.lastgroup != "phone" and self._value(n) is not None:
                    break
        return last

    def phone(self, v: str) -> str | None:
        head = re.match(r"\+\d{1,3}(?!\d)|", v)[0]
        rest = v[len(head) :]
        digits = re.sub(r"\D", "", rest)
        if not 6 <= len(digits) <= 14:
            return None
        return head + _spell(rest, self._digits("phone", digits))

    def email(self, m: re.Match) -> str:
        return f"{self._letters('email', m[1], ALPHABETS)}@{m[2]}"

    def secret(self, m: re.Match) -> str:
        return m[1] + self._letters("secret", m[2], HEX[m[2] != m[2].lower() :])

    def _value(self, m: re.Match) -> str | None:
        return getattr(self, "date" if m.lastgroup == "stamp" else m.lastgroup)(m[0])

    def others(self, text: str, start: int, end: int) -> list[tuple[int, int, str, str]]:
        """Dates, addresses, social security and phone numbers in a part of a text."""
        out, at = [], start
        while m := NUMERIC.search(text, at, end):
            kind, at = "date" if m.lastgroup == "stamp" else m.lastgroup, m.end()
            if kind in self.kinds:
                if kind == "phone":
                    at = self.phone_end(text, m.start(), at)
                    new = self.phone(text[m.start() : at])
                else:
                    new = self._value(m)
                if new is not None:
                    out.append((m.start(), at, kind, new))
        return out

    def numbers(self, text: str) -> list[tuple[int, int, str, str]]:
        """Cards in their usual grouping first, then the other kinds in what is left, then cards in any grouping."""
        found: list[tuple[int, int, str, str]] = []
        cards = "card" in self.kinds and RUN.search(text)
        for look in (lambda *part: self.cards(*part, True) if cards else [], self.others, lambda *part: self.cards(*part, False) if cards else []):
            edges = [0, *(x for start, end, *_ in found for x in (start, end)), len(text)]
            found = sorted(found + [f for part in zip(edges[::2], edges[1::2]) for f in look(text, *part)])
        return found

    def replace(self, text: str | None) -> tuple[str | None, dict[str, int]]:
        """The text with its values replaced, and how many of each kind."""
        counts: dict[str, int] = {}
        if not text or not _HINT.search(text):
            return text, counts
        done: list[tuple[int, int, str, str]] = []
        if "@" in text and "email" in self.kinds:
            done += [(m.start(), m.end(), "email", self.email(m)) for m in EMAIL.finditer(text)]
        if "secret" in self.kinds:
            done += [(m.start(), m.end(), "secret", self.secret(m)) for m in SECRET.finditer(text)]
        done += self.numbers(text)
        out, at = [], 0
        for start, end, kind, new in sorted(done):
            if start >= at:
                out += [text[at:start], new]
                at = end
                counts[kind] = counts.get(kind, 0) + 1
        out.append(text[at:])
        return "".join(out), counts


def session_key(spark: SparkSession, demonstration: str | None = None) -> str:
    """The key in the session's settings; without one an error, or with a warning the ``demonstration`` key, which hides nothing from readers of the source."""
    key = spark.conf.get(KEY_SETTING, None)
    if not key:
        if demonstration is None:
            raise ValueError(f"set {KEY_SETTING}")
        warnings.warn(f"{KEY_SETTING} is not set: pseudonyms are made with a public demonstration key", stacklevel=2)
    return key or demonstration


def pseudonymise(docs: DataFrame, key: str, kinds: tuple[str, ...] = KINDS, text: str = "text", counts: str | None = None) -> DataFrame:
    """``docs`` with pseudonyms in ``text``; with ``counts``, one more column of that name maps kinds to numbers of values."""
    if not key:
        raise ValueError("pseudonyms need a key")
    ship_package(docs.sparkSession)
    kept = without(docs, counts) if counts else docs
    at = kept.columns.index(text)
    fields = [*kept.schema.fields, *([T.StructField(counts, T.MapType(T.StringType(), T.IntegerType()))] if counts else [])]

    def run(batches):
        worker = Pseudonyms(key.encode(), kinds)
        for b in bounded_slices(batches, f"c{at}"):
            got = [worker.replace(t) for t in b.column(at).to_pylist()]
            columns = list(b.columns)
            columns[at] = pa.array([t for t, _ in got], pa.string())
            if counts:
                columns.append(pa.array([list(c.items()) for _, c in got], pa.map_(pa.string(), pa.int32())))
            yield pa.RecordBatch.from_arrays(columns, names=[f"c{i}" for i in range(len(columns))])

    return mapped(kept, run, fields)
