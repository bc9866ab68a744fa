"""Format-preserving pseudonyms for personal data and secrets.

A value that passes its validation (check digit, calendar, octets, numbering plan) is mapped by
a keyed Feistel permutation of the set of all valid values of its format. Separators and
validity stay, and so do lengths but for the octets of network addresses and days and months of
one digit; equal values get equal pseudonyms in every document, different values different
ones. No table is kept and rows are independent: no exchange.
"""

from __future__ import annotations

import datetime
import hashlib
import re
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .blocks import trimmed

ROUNDS = 8


class Feistel:
    """Keyed permutation of range(size), by cycle walking in the next power of four."""

    def __init__(self, key: bytes, domain: str, size: int) -> None:
        self.size, self.half = size, max(1, ((max(size - 1, 1)).bit_length() + 1) // 2)
        self.mask, self.width = (1 << self.half) - 1, (self.half + 7) // 8
        seeded = hashlib.blake2b(key=key[:64], person=hashlib.blake2b(domain.encode(), digest_size=16).digest(), digest_size=self.width)
        self.rounds = []
        for i in range(ROUNDS):
            h = seeded.copy()
            h.update(bytes([i]))
            self.rounds.append(h)

    def _f(self, i: int, right: int) -> int:
        h = self.rounds[i].copy()
        h.update(right.to_bytes(self.width, "little"))
        return int.from_bytes(h.digest(), "little") & self.mask

    def apply(self, x: int) -> int:
        while True:
            left, right = x >> self.half, x & self.mask
            for i in range(ROUNDS):
                left, right = right, left ^ self._f(i, right)
            x = left << self.half | right
            if x < self.size:
                return x

    def invert(self, x: int) -> int:
        while True:
            left, right = x >> self.half, x & self.mask
            for i in reversed(range(ROUNDS)):
                left, right = right ^ self._f(i, left), left
            x = left << self.half | right
            if x < self.size:
                return x


def luhn_digit(digits: str) -> int:
    """The check digit that belongs behind these digits."""
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = int(c) * (2 - i % 2)
        total += d - 9 * (d > 9)
    return -total % 10


_DIGITS, _LOWER, _UPPER = "0123456789", "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
_EPOCH, _LAST = datetime.date(1900, 1, 1).toordinal(), datetime.date(2099, 12, 31).toordinal()
_MOD97 = {c: str(i) for i, c in enumerate(_DIGITS + _UPPER)}


def iban_valid(s: str) -> bool:
    return int("".join(_MOD97[c] for c in s[4:] + s[:4])) % 97 == 1


class Pseudonymiser:
    """Finds and replaces: cards, bank accounts, phones, social security numbers, addresses of
    machines and mail, dates, access keys and secrets behind an assignment."""

    def __init__(self, key: bytes) -> None:
        self.key = key
        self.boxes: dict[tuple[str, int], Feistel] = {}
        secret = r"""(?<![A-Za-z0-9])(?i:password|passwd|pwd|token|secret|api[_-]?key)\s*[=:]\s*["']?"""
        self.kinds: list[tuple[str, str, Callable[[str], str | None]]] = [
            ("secret", rf"{secret}[A-Za-z0-9_\-+/]{{8,}}", self._secret),
            ("access_key", r"(?<![A-Za-z0-9])(?:AKIA|ASIA)[A-Z0-9]{16}(?![A-Za-z0-9])", lambda s: s[:4] + self._letters("access_key", s[4:])),
            ("email", r"(?<![A-Za-z0-9._%+\-])[A-Za-z0-9._%+\-]{1,64}@(?:[A-Za-z0-9\-]+\.)+[A-Za-z]{2,}", self._email),
            ("iban", r"(?<![A-Za-z0-9])[A-Z]{2}\d{2}[A-Z0-9]{11,30}(?![A-Za-z0-9])", self._iban),
            ("date", r"(?<![\d./\-])(?:\d{4}-\d{2}-\d{2}|\d{1,2}/\d{1,2}/\d{4}|\d{1,2}\.\d{1,2}\.\d{4})(?![\d/\-]|\.\d)", self._date),
            ("ip", r"(?<![\d.])(?:\d{1,3}\.){3}\d{1,3}(?!\d|\.\d)", self._ip),
            ("ssn", r"(?<![\d\-])\d{3}-\d{2}-\d{4}(?![\d\-])", self._ssn),
            ("phone", r"(?<![\d+])\+\d{1,3}[ .\-]?\(?\d{1,4}\)?(?:[ .\-]?\d{2,4}){2,4}(?!\d)|(?<![\d\-(])\(?\d{3}\)?[ .\-]\d{3}[ .\-]\d{4}(?![\d\-])", self._phone),
            ("card", r"(?<![\dA-Za-z])\d(?:[ \-]?\d){12,18}(?![\dA-Za-z])", self._card),
        ]
        self.pattern = re.compile("|".join(f"(?P<{name}>{p})" for name, p, _ in self.kinds), re.ASCII)
        self.replace = {name: f for name, _, f in self.kinds}
        #: Every kind holds one of these (secrets the third, access keys the last); most texts are done after one look.
        self.hint = re.compile(r"[\d@]|[=:]\s*[\"']?[A-Za-z0-9_\-+/]{8}|A[KS]IA")

    def box(self, domain: str, size: int) -> Feistel:
        if (domain, size) not in self.boxes:
            self.boxes[domain, size] = Feistel(self.key, f"{domain}/{size}", size)
        return self.boxes[domain, size]

    def _digits(self, domain: str, digits: str) -> str:
        return str(self.box(domain, 10 ** len(digits)).apply(int(digits))).zfill(len(digits)) if digits else ""

    def _letters(self, domain: str, text: str) -> str:
        """Permutes the characters' values, each within its own class; other characters stay."""
        sets = [next((a for a in (_DIGITS, _LOWER, _UPPER) if c in a), None) for c in text]
        value = size = 0
        for c, a in zip(text, sets, strict=True):
            if a:
                value, size = value * len(a) + a.index(c), (size or 1) * len(a)
        if not size:
            return text
        shape = "".join("." if a is None else a[0] for a in sets)
        value, out = self.box(f"{domain}/{shape}", size).apply(value), []
        for c, a in zip(reversed(text), reversed(sets), strict=True):
            if a:
                value, i = divmod(value, len(a))
                c = a[i]
            out.append(c)
        return "".join(reversed(out))

    @staticmethod
    def _refill(like: str, digits: str) -> str:
        it = iter(digits)
        return "".join(next(it) if c in _DIGITS else c for c in like)

    def _card(self, s: str) -> str | None:
        d = re.sub(r"\D", "", s)
        if d[0] not in "23456" or len(set(d)) == 1 or luhn_digit(d[:-1]) != int(d[-1]):
            return None
        body = d[0] + self._digits("card", d[1:-1])
        return self._refill(s, body + str(luhn_digit(body)))

    def _phone(self, s: str) -> str | None:
        d = re.sub(r"\D", "", s)
        if not 7 <= len(d) <= 15:
            return None
        country = 1 if s[0] == "+" else 0
        return self._refill(s, d[:country] + self._digits("phone", d[country:]))

    def _ssn(self, s: str) -> str | None:
        a, b, c = (int(x) for x in s.split("-"))
        if a in (0, 666) or a >= 900 or not b or not c:
            return None
        areas = [x for x in range(1, 900) if x != 666]
        v = self.box("ssn", 898 * 99 * 9999).apply(((a - 1 - (a > 666)) * 99 + b - 1) * 9999 + c - 1)
        v, c = divmod(v, 9999)
        a, b = divmod(v, 99)
        return f"{areas[a]:03d}-{b + 1:02d}-{c + 1:04d}"

    def _ip(self, s: str) -> str | None:
        parts = [int(x) for x in s.split(".")]
        if max(parts) > 255:
            return None
        v = self.box("ip", 1 << 32).apply(int.from_bytes(bytes(parts), "big"))
        return ".".join(map(str, v.to_bytes(4, "big")))

    def _date(self, s: str) -> str | None:
        sep = next(c for c in s if c not in _DIGITS)
        x = [int(p) for p in s.split(sep)]
        order = "ymd" if sep == "-" else "mdy" if sep == "/" and x[0] <= 12 else "dmy"
        f = dict(zip(order, x, strict=True))
        try:
            day = datetime.date(f["y"], f["m"], f["d"]).toordinal()
        except ValueError:
            return None
        if not _EPOCH <= day <= _LAST:
            return None
        # each way of writing has its own set of valid values, so that writing back is unambiguous
        # months first are read whenever they can be, so days over 12 form the other set
        box = self.box("date", _LAST - _EPOCH + 1)
        new = datetime.date.fromordinal(_EPOCH + box.apply(day - _EPOCH))
        while sep == "/" and order == "dmy" and new.day <= 12:
            new = datetime.date.fromordinal(_EPOCH + box.apply(new.toordinal() - _EPOCH))
        g = {"y": f"{new.year:04d}", "m": f"{new.month:02d}", "d": f"{new.day:02d}"}
        return sep.join(g[c] for c in order)

    def _iban(self, s: str) -> str | None:
        if not iban_valid(s):
            return None
        body = self._letters("iban", s[4:])
        check = 98 - int("".join(_MOD97[c] for c in body + s[:2] + "00")) % 97
        return f"{s[:2]}{check:02d}{body}"

    def _email(self, s: str) -> str:
        local, at, host = s.partition("@")
        return self._letters("email", local) + at + host

    def _secret(self, s: str) -> str | None:
        head = re.match(r"""[^=:]*[=:]\s*["']?""", s).group()
        return head + self._letters("secret", s[len(head) :])

    def run(self, text: str) -> tuple[str, dict[str, int]]:
        counts: dict[str, int] = {}
        if not self.hint.search(text):
            return text, counts

        def one(m: re.Match) -> str:
            new = self.replace[m.lastgroup](m.group())
            if new is None:
                return m.group()
            counts[m.lastgroup] = counts.get(m.lastgroup, 0) + 1
            return new

        return self.pattern.sub(one, text), counts


def pseudonymise(docs: DataFrame, key: bytes, text_col: str = "text", kinds_col: str | None = "pii_kinds") -> DataFrame:
    """docs with text_col pseudonymised and, if kinds_col is given, a map kind -> replacements.

    Null texts stay null, empty ones empty; each row is independent of all others; other
    columns stay, but one named like kinds_col is replaced.
    """
    kept = [f for f in docs.schema.fields if f.name != kinds_col]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = Pseudonymiser(key)
        for batch in batches:
            done = [(None, {}) if x is None else own.run(x) for x in batch.column(text_col).to_pylist()]
            columns = [pa.array([t for t, _ in done], pa.string()) if n == text_col else batch.column(n) for n in batch.schema.names]
            if kinds_col:
                columns.append(pa.array([list(c.items()) for _, c in done], pa.map_(pa.string(), pa.int32())))
            yield pa.RecordBatch.from_arrays(columns, names=[*batch.schema.names, *[kinds_col] * bool(kinds_col)])

    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in kept), *[f"`{kinds_col}` map<string,int>"] * bool(kinds_col)])
    return docs.select(*(F.col(f"`{f.name}`") for f in kept)).mapInArrow(lambda b: trimmed(run(b)), schema)
