"""Personal data replaced by format-preserving Feistel pseudonyms.

What is found: e-mail addresses, payment-card and other long numbers, IBANs,
telephone numbers, social-security numbers, IPv4 addresses, calendar dates and
hexadecimal secrets.  A value is checked as its format allows (Luhn digit,
IBAN remainder, octets, calendar), turned into an integer of its format's
domain, permuted there by a keyed Feistel network with cycle walking, and
written back in the same format: a valid card number stays a valid card
number, a date a date.  The permutation depends on the key and the format only,
so equal values stay linked across documents, and it can be undone with the
key.  Where a value ends is told by its own shape (the country's length of an
IBAN, the groups of a card number), not by what stands beside it; what a match
holds beyond the value is searched again.

Dates are read with two-digit days and months and four-digit years; other
spellings of dates, names and postal addresses are not looked for.

Null texts stay null; empty texts stay empty; whole texts are read; equal rows
get equal results; an empty table gives an empty result; other columns pass
through (a column named like one of the counters gives way to it).
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from datetime import date, timedelta

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from rowsketch.llm.common import named

ROUNDS = 8
#: For tests and examples; a deployment passes its own.
EXAMPLE_KEY = b"example key, not a secret"
FIRST_DAY = date(1900, 1, 1)
DAYS = (date(2100, 1, 1) - FIRST_DAY).days
KINDS = ("email", "card", "iban", "phone", "ssn", "ip", "date", "number", "secret")


def permute(x: int, size: int, key: bytes, tweak: bytes, undo: bool = False) -> int:
    """A keyed permutation of 0 .. size-1: Feistel over two halves, walked until it lands in the domain."""
    if size < 2:
        return x
    half = 1
    while half * half < size:
        half += 1 if half < 64 else half // 64 + 1
    while True:
        left, right = divmod(x, half)
        for r in range(ROUNDS - 1, -1, -1) if undo else range(ROUNDS):
            other = left if undo else right
            word = hashlib.blake2b(b"%d|%d|%d|" % (r, size, other) + tweak, key=key[:64], digest_size=16 + half.bit_length() // 8).digest()
            f = int.from_bytes(word, "big") % half
            if undo:
                left, right = (right - f) % half, left
            else:
                left, right = right, (left + f) % half
        x = left * half + right
        if x < size:
            return x


def luhn_digit(payload: str) -> str:
    total = 0
    for k, c in enumerate(reversed(payload)):
        d = int(c) * (2 if k % 2 == 0 else 1)
        total += d - 9 if d > 9 else d
    return str(-total % 10)


class Pseudonyms:
    """Value to pseudonym, by kind; ``undo`` turns pseudonyms back."""

    def __init__(self, key: bytes = EXAMPLE_KEY, undo: bool = False):
        self.key, self.undo = key, undo

    def _number(self, x: int, size: int, tweak: str) -> int:
        return permute(x, size, self.key, tweak.encode(), self.undo)

    def digits(self, s: str, tweak: str) -> str:
        """The digits of ``s`` permuted together, everything else in its place."""
        d = "".join(c for c in s if "0" <= c <= "9")
        if not d:
            return s
        new = iter(str(self._number(int(d), 10 ** len(d), f"{tweak}{len(d)}")).zfill(len(d)))
        return "".join(next(new) if "0" <= c <= "9" else c for c in s)

    def mixed(self, s: str, tweak: str) -> str:
        """Small letters, capitals and digits permuted within their alphabets, as one number; the rest stays."""
        x, size = 0, 1
        sets = []
        for c in s:
            low, n = ("a", 26) if "a" <= c <= "z" else ("A", 26) if "A" <= c <= "Z" else ("0", 10) if "0" <= c <= "9" else ("", 0)
            sets.append((low, n))
            if n:
                x, size = x * n + ord(c) - ord(low), size * n
        shape = "".join(low or "-" for low, _ in sets)
        x = self._number(x, size, tweak + shape)
        out = []
        for c, (low, n) in zip(reversed(s), reversed(sets)):
            if n:
                x, d = divmod(x, n)
                c = chr(ord(low) + d)
            out.append(c)
        return "".join(reversed(out))

    def email(self, s: str) -> str | None:
        name, _, host = s.rpartition("@")
        labels = host.split(".")
        whole = self.mixed(name + "@" + ".".join(labels[:-1]), "email")
        return whole + "." + labels[-1]

    def card(self, s: str) -> str | None:
        """A valid number; ``None`` for one that is not."""
        d = re.sub(r"\D", "", s)
        if luhn_digit(d[:-1]) != d[-1]:
            return None
        head = "".join(_GROUPS.findall(s)[:4]) if card_head(s) != len(s) else ""
        body = d[:-1]
        while True:  # a pseudonym whose leading groups are a card of their own would be read as that
            body = str(self._number(int(body), 10 ** (len(d) - 1), f"card{len(d)}")).zfill(len(d) - 1)
            new = body + luhn_digit(body)
            if not head or luhn_digit(new[: len(head) - 1]) != new[len(head) - 1]:
                break
        new = iter(new)
        return "".join(next(new) if "0" <= c <= "9" else c for c in s)

    def number(self, s: str) -> str | None:
        """A long number that is no valid card: permuted among the numbers that are none."""
        d = re.sub(r"\D", "", s)
        if len(d) < 13:
            return None
        # payload and the distance of the last digit from the valid one, 1 to 9
        gap = (int(d[-1]) - int(luhn_digit(d[:-1]))) % 10
        if not gap:
            return None
        x = self._number(int(d[:-1]) * 9 + gap - 1, 9 * 10 ** (len(d) - 1), f"number{len(d)}")
        body, gap = divmod(x, 9)
        payload = str(body).zfill(len(d) - 1)
        new = iter(payload + str((int(luhn_digit(payload)) + gap + 1) % 10))
        return "".join(next(new) if "0" <= c <= "9" else c for c in s)

    def iban(self, s: str) -> str | None:
        flat = s.replace(" ", "")
        value = lambda t: int("".join(str(int(c, 36)) for c in t))
        if value(flat[4:] + flat[:4]) % 97 != 1:
            return None
        body = self.mixed(flat[4:], "iban" + flat[:2])
        check = 98 - value(body + flat[:2] + "00") % 97
        new = iter(flat[:2] + f"{check:02d}" + body)
        return "".join(next(new) if c != " " else c for c in s)

    def take(self, kind: str, s: str) -> tuple[str, str, int]:
        """What is found at the beginning of a match: its kind ('' for none), what replaces it, and its length."""
        rest = ""
        if kind == "iban":
            s = s[: iban_head(s)]
        elif kind == "card":
            head = card_head(s)
            nineteen = tuple(map(len, _GROUPS.findall(s))) == (4, 4, 4, 4, 3)
            if not nineteen or self.card(s[:head]) is not None:
                s = s[:head]
            elif self.card(s) is None:
                s, rest = s[:head], s[head:]
        new = getattr(self, kind)(s)
        if new is None and kind == "card":
            kind, new = "number", self.number(s)
            while rest and self.card(new + rest) is not None:  # else it would be read as a longer card
                new = self.number(new)
        if new is not None:
            return kind, new, len(s)
        first = _FIRST.match(s).end()
        return "", s[:first], first

    def phone(self, s: str) -> str | None:
        d = sum("0" <= c <= "9" for c in s)
        if not 7 <= d <= 15:
            return None
        m = re.match(r"\+\d{1,3}(?=\D)", s)
        head = m.group() if m else ""
        return head + self.digits(s[len(head) :], "phone" + head)

    def ssn(self, s: str) -> str | None:
        return self.digits(s, "ssn")

    def ip(self, s: str) -> str | None:
        parts = [int(p) for p in s.split(".")]
        if max(parts) > 255 or any(len(p) > 1 and p[0] == "0" for p in s.split(".")):
            return None
        x = self._number(int.from_bytes(bytes(parts), "big"), 2**32, "ip")
        return ".".join(map(str, x.to_bytes(4, "big")))

    def date(self, s: str) -> str | None:
        f = re.findall(r"\d+", s)
        mark = re.search(r"\D", s).group()
        year = 0 if len(f[0]) == 4 else 2
        month, day = (1, 2) if year == 0 else (0, 1) if mark == "/" else (1, 0)
        try:
            x = (date(int(f[year]), int(f[month]), int(f[day])) - FIRST_DAY).days
        except ValueError:
            return None
        if not 0 <= x < DAYS:
            return None
        y = FIRST_DAY + timedelta(days=self._number(x, DAYS, "date"))
        out = [""] * 3
        out[year], out[month], out[day] = f"{y.year:04d}", f"{y.month:02d}", f"{y.day:02d}"
        return mark.join(out)

    def secret(self, s: str) -> str | None:
        if s.isdigit() or not any("0" <= c <= "9" for c in s):
            return None
        upper = s.upper() == s
        x = self._number(int(s, 16), 16 ** len(s), f"secret{len(s)}")
        new = f"{x:0{len(s)}x}"
        return new.upper() if upper else new


#: One pattern for each kind, tried in this order where several begin.
PATTERNS = {
    "email": r"[^\s@<>()\[\]{}|,;:\"'=]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)*\.[A-Za-z]{2,}",
    "iban": r"(?<![A-Za-z0-9])[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?(?![A-Za-z0-9])",
    "secret": r"(?<![0-9A-Za-z])(?:[0-9a-f]{32,128}|[0-9A-F]{32,128})(?![0-9A-Za-z])",
    "date": r"(?<![\d.])(?:\d{4}-\d{2}-\d{2}|\d{4}/\d{2}/\d{2}|\d{2}[./-]\d{2}[./-]\d{4})(?!\d|[./-]\d)",
    "ssn": r"(?<![\d-])\d{3}-\d{2}-\d{4}(?![\d-])",
    "ip": r"(?<![\d.])\d{1,3}(?:\.\d{1,3}){3}(?!\d|\.\d)",
    "card": r"(?<!\d)(?:\d[ -]?){12,18}\d(?!\d)",
    "phone": r"(?<![\w+])(?:\+\d{1,3}[ .-]?(?:\(\d{1,4}\)[ .-]?)?\d{2,4}(?:[ .-]?\d{2,4}){1,4}|\(\d{3}\)[ .-]?\d{3}[ .-]?\d{4}|\d{3}[.-]\d{3}[.-]\d{4})(?!\d)",
}
#: Characters of an IBAN by country.
IBAN_LENGTHS = {
    "AD": 24, "AE": 23, "AL": 28, "AT": 20, "AZ": 28, "BA": 20, "BE": 16, "BG": 22, "BH": 22, "BR": 29, "BY": 28, "CH": 21, "CR": 22, "CY": 28, "CZ": 24, "DE": 22,
    "DK": 18, "DO": 28, "EE": 20, "EG": 29, "ES": 24, "FI": 18, "FO": 18, "FR": 27, "GB": 22, "GE": 22, "GI": 23, "GL": 18, "GR": 27, "GT": 28, "HR": 21, "HU": 28,
    "IE": 22, "IL": 23, "IQ": 23, "IS": 26, "IT": 27, "JO": 30, "KW": 30, "KZ": 20, "LB": 28, "LC": 32, "LI": 21, "LT": 20, "LU": 20, "LV": 21, "LY": 25, "MC": 27,
    "MD": 24, "ME": 22, "MK": 19, "MR": 27, "MT": 31, "MU": 30, "NL": 18, "NO": 15, "PK": 24, "PL": 28, "PS": 29, "PT": 25, "QA": 29, "RO": 24, "RS": 22, "SA": 24,
    "SC": 31, "SE": 24, "SI": 19, "SK": 24, "SM": 27, "ST": 25, "SV": 28, "TL": 23, "TN": 24, "TR": 26, "UA": 29, "VA": 22, "VG": 24, "XK": 20,
}
#: Digits of a card number's groups, as cards print them.
CARD_GROUPS = ((4, 4, 4, 4), (4, 6, 5), (4, 6, 4))
_GROUPS = re.compile(r"\d+")
_FIRST = re.compile(r"[^ -]*[ -]?")


def iban_head(s: str) -> int:
    """Where the IBAN at the beginning of a match ends, by its country's length; the whole match for other countries."""
    wanted, seen = IBAN_LENGTHS.get(s[:2], 0), 0
    for k, c in enumerate(s):
        seen += c != " "
        if seen == wanted:
            return k + 1 if k + 1 == len(s) or s[k + 1] == " " else len(s)
    return len(s)


def card_head(s: str) -> int:
    """Where the card number at the beginning of a match ends, by its groups; the whole match for other layouts."""
    groups = list(_GROUPS.finditer(s))
    sizes = tuple(len(g.group()) for g in groups)
    if sizes[0] >= 13:
        return groups[0].end()
    for layout in CARD_GROUPS:
        if sizes[: len(layout)] == layout:
            return groups[len(layout) - 1].end()
    return len(s)


_ANY = re.compile("|".join(f"(?P<{k}>{p})" for k, p in PATTERNS.items()))
_HINT = re.compile(r"[0-9@]")


def replace(text: str, make: Pseudonyms) -> tuple[str, dict[str, int]]:
    """The text with its personal data replaced, and how many values of each kind were."""
    found: dict[str, int] = {}
    if not _HINT.search(text):
        return text, found

    out, at = [], 0
    while m := _ANY.search(text, at):
        kind, new, length = make.take(m.lastgroup, m.group())
        out += (text[at : m.start()], new)
        at = m.start() + length
        if kind:
            found[kind] = found.get(kind, 0) + 1
    out.append(text[at:])
    return "".join(out), found


def pseudonymise(docs: DataFrame, *, key: bytes = EXAMPLE_KEY, undo: bool = False, text: str = "text") -> DataFrame:
    """The input with ``text`` replaced and a counter ``n_<kind>`` for each kind."""
    counters = [f"n_{k}" for k in KINDS]
    names = [c for c in docs.columns if c not in counters]
    # plain names on the way through Python
    plain = [f"c{k}" for k in range(len(names))]
    schema = T.StructType([T.StructField(p, docs.schema[c].dataType if c != text else T.StringType()) for p, c in zip(plain, names)] + [T.StructField(c, T.LongType()) for c in counters])
    at = names.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        make = Pseudonyms(key, undo)
        for rb in batches:
            texts, counts = [], []
            for t in rb.column(at):
                t = t.as_py()
                new, found = (None, {}) if t is None else replace(t, make)
                texts.append(new)
                counts.append(found)
            columns = [pa.array(texts, pa.string()) if k == at else c for k, c in enumerate(rb.columns)]
            columns += [pa.array([f.get(k, 0) for f in counts], pa.int64()) for k in KINDS]
            yield pa.RecordBatch.from_arrays(columns, plain + counters)

    sent = docs.select(*[(named(c) if c != text else named(c).cast("string")).alias(p) for p, c in zip(plain, names)])
    return sent.mapInArrow(run, schema).toDF(*names, *counters)


__all__ = ["EXAMPLE_KEY", "IBAN_LENGTHS", "KINDS", "Pseudonyms", "luhn_digit", "permute", "pseudonymise", "replace"]
