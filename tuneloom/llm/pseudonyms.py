"""Format-preserving pseudonyms: validated personal numbers, dates and addresses, permuted within their format by a keyed
Feistel network.

Each kind maps its valid values one to one onto 0 .. N-1, the network permutes that range (walking its cycle until the
result lies inside), and the inverse map writes the result in the layout of the original. Equal values therefore get equal
pseudonyms in every document and layout (a day written in three ways is one day again, an address in capitals the same
address), different values different ones, and every pseudonym is valid again. What fails validation is left as it is.

A card or IBAN may be followed by more digits or capitals after a blank or hyphen. Where the match of such a number has
groups, it is read up to the end of any of them: a card up to the first that makes it valid, an IBAN up to its country's
length, else up to the last that makes it valid. Values are permuted again until they are read back to the same length.

Edges: a 19-digit card in groups whose first 16 digits are by chance valid is read as one of 16; digits before a card may,
with its new digits, form a valid number and are then not read back; a date that could be day or month first is read day first; a null text stays null; an empty text stays empty; matches that overlap are taken from the left, longest kind first;
repeated rows give repeated results; an empty table gives an empty result.
"""

from __future__ import annotations

import calendar
import datetime
import hashlib
import re
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import batch_of, column, pieces

ROUNDS = 10
_FIRST_DAY, _LAST_DAY = datetime.date(1900, 1, 1).toordinal(), datetime.date(2099, 12, 31).toordinal()


class Feistel:
    """A keyed permutation of 0 .. size-1."""

    def __init__(self, key: bytes):
        self.key = hashlib.blake2b(key, digest_size=32).digest()

    def _round(self, kind: str, no: int, value: int, bits: int) -> int:
        data = f"{kind}|{no}|{bits}|{value}".encode()
        size = (bits + 7) // 8
        if size <= 64:
            raw = hashlib.blake2b(data, key=self.key, digest_size=size).digest()
        else:
            raw = hashlib.shake_256(self.key + data).digest(size)
        return int.from_bytes(raw, "big") & ((1 << bits) - 1)

    def __call__(self, value: int, size: int, kind: str, back: bool = False) -> int:
        if size < 2:
            return value
        half = max(1, ((size - 1).bit_length() + 1) // 2)
        mask = (1 << half) - 1
        while True:
            left, right = value >> half, value & mask
            for no in range(ROUNDS - 1, -1, -1) if back else range(ROUNDS):
                if back:
                    left, right = right ^ self._round(kind, no, left, half), left
                else:
                    left, right = right, left ^ self._round(kind, no, right, half)
            value = left << half | right
            if value < size:
                return value


def luhn(digits: str) -> bool:
    total = 0
    for i, d in enumerate(reversed(digits)):
        n = int(d) * (1 + i % 2)
        total += n - 9 * (n > 9)
    return total % 10 == 0


def iban_rest(text: str) -> int:
    return int("".join(str(int(c, 36)) for c in text[4:] + text[:4])) % 97


def _fill(layout: str, new: str) -> str:
    """New digits in the places of the layout's digits."""
    it = iter(new)
    return "".join(next(it) if c.isdigit() else c for c in layout)


def card(text: str, f: Feistel, back: bool) -> str | None:
    digits = re.sub(r"\D", "", text)
    if not (13 <= len(digits) <= 19 and digits[0] in "23456" and luhn(digits)):
        return None
    n = len(digits) - 2
    body = digits[0] + str(f(int(digits[1:-1]), 10**n, f"card{len(digits)}{digits[0]}", back)).zfill(n)
    return _fill(text, next(body + c for c in "0123456789" if luhn(body + c)))


def phone(text: str, f: Feistel, back: bool) -> str | None:
    digits = re.sub(r"\D", "", text)
    lead, d = digits[:-10], digits[-10:]
    if len(d) != 10 or lead not in ("", "1") or d[0] in "01" or d[3] in "01":
        return None
    v = ((int(d[:3]) - 200) * 800 + int(d[3:6]) - 200) * 10000 + int(d[6:])
    v = f(v, 800 * 800 * 10000, "phone", back)
    return _fill(text, f"{lead}{v // 8000000 + 200}{v // 10000 % 800 + 200}{v % 10000:04}")


def social(text: str, f: Feistel, back: bool) -> str | None:
    a, b, c = (int(x) for x in text.split("-"))
    if not (0 < a < 900 and a != 666 and b and c):
        return None
    v = f((((a - 1 - (a > 666)) * 99) + b - 1) * 9999 + c - 1, 898 * 99 * 9999, "social", back)
    a = v // (99 * 9999) + 1
    return f"{a + (a >= 666):03}-{v // 9999 % 99 + 1:02}-{v % 9999 + 1:04}"


def address(text: str, f: Feistel, back: bool) -> str | None:
    parts = text.split(".")
    if any(int(p) > 255 or (len(p) > 1 and p[0] == "0") for p in parts):
        return None
    v = f(int.from_bytes(bytes(map(int, parts)), "big"), 1 << 32, "address", back)
    return ".".join(map(str, v.to_bytes(4, "big")))


def iban(text: str, f: Feistel, back: bool) -> str | None:
    plain = text.replace(" ", "")
    if not 15 <= len(plain) <= 34 or iban_rest(plain) != 1:
        return None
    digits = re.sub(r"\D", "", plain[4:])
    new = _fill(plain[4:], str(f(int(digits or 0), 10 ** len(digits), "iban" + plain[:2] + re.sub(r"\d", "0", plain[4:]), back)).zfill(len(digits)))
    body = plain[:2] + f"{98 - iban_rest(plain[:2] + '00' + new):02}" + new
    it = iter(body)
    return "".join(c if c == " " else next(it) for c in text)


_DATES = ((re.compile(r"(\d{4})([-/.])(\d{2})\2(\d{2})$"), "ymd"), (re.compile(r"(\d{2})([-/.])(\d{2})\2(\d{4})$"), "dmy"))


def date(text: str, f: Feistel, back: bool) -> str | None:
    """Year first, or day first; with a second number over 12, month first."""
    for shape, order in _DATES:
        if not (m := shape.match(text)):
            continue
        a, sep, b, c = m.groups()
        y, mo, d = (int(a), int(b), int(c)) if order == "ymd" else (int(c), int(b), int(a))
        swap = order == "dmy" and mo > 12
        if swap:
            mo, d = d, mo
        if not (1900 <= y <= 2099 and 1 <= mo <= 12 and 1 <= d <= calendar.monthrange(y, mo)[1]):
            return None
        # one permutation of the days for all layouts; a day keeps its side of 12, so that the order of day and month is read
        # again as it was
        v, low = datetime.date(y, mo, d).toordinal() - _FIRST_DAY, d <= 12
        while True:
            v = f(v, _LAST_DAY - _FIRST_DAY + 1, "date", back)
            new = datetime.date.fromordinal(_FIRST_DAY + v)
            if (new.day <= 12) == low:
                break
        if order == "ymd":
            return f"{new.year}{sep}{new.month:02}{sep}{new.day:02}"
        one, two = (new.month, new.day) if swap else (new.day, new.month)
        return f"{one:02}{sep}{two:02}{sep}{new.year}"
    return None


def _classes(text: str) -> list[str]:
    return ["0123456789" if c.isdigit() else "abcdefghijklmnopqrstuvwxyz" if c.islower() else c for c in text]


def mail(text: str, f: Feistel, back: bool) -> str | None:
    """Letters and digits of the local part, each within its class; the domain stays. Addresses that differ in case alone are one:
    capitals stay where they were."""
    local, at, domain = text.partition("@")
    plain = local.lower()
    kinds = _classes(plain)
    size, v = 1, 0
    for c, k in zip(plain, kinds):
        if len(k) > 1:
            v, size = v * len(k) + k.index(c), size * len(k)
    v = f(v, size, "mail" + re.sub("[a-z]", "a", re.sub("[0-9]", "0", plain)), back)
    out = []
    for c, k in zip(reversed(local), reversed(kinds)):
        if len(k) > 1:
            v, r = divmod(v, len(k))
            out.append(k[r].upper() if c.isupper() else k[r])
        else:
            out.append(k)
    return "".join(reversed(out)) + at + domain


KINDS = {
    "mail": (r"[A-Za-z0-9][A-Za-z0-9._%+\-]{0,63}@[A-Za-z0-9\-]+(?:\.[A-Za-z0-9\-]+)*\.[A-Za-z]{2,}", mail),
    "iban": (r"\b[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,4})?\b", iban),
    "date": (r"(?<![\d.])(?:\d{4}([-/.])\d{2}\1\d{2}|\d{2}([-/.])\d{2}\2\d{4})(?![\d])(?!\.\d)", date),
    "address": (r"(?<![\d.])\d{1,3}(?:\.\d{1,3}){3}(?!\d)(?!\.\d)", address),
    "social": (r"(?<![\d\-])\d{3}-\d{2}-\d{4}(?![\d\-])", social),
    "phone": (r"(?<![\d+])(?:\+?1[ .\-]?)?(?:\(\d{3}\) ?|\d{3}[ .\-])\d{3}[ .\-]\d{4}(?!\d)", phone),
    "card": (r"(?<![\d])\d(?:[ \-]?\d){12,18}(?!\d)", card),
}

#: Characters of an IBAN by country.
IBAN_LENGTHS = {c: n for n, cs in {15: "NO", 16: "BE", 18: "DK FI FO GL NL", 19: "MK SI", 20: "AT BA EE KZ LT LU XK", 21: "CH CR HR LI LV", 22: "BG BH DE GB GE IE ME RS", 23: "AE GI IL TL", 24: "AD CZ ES MD PK RO SA SE SK TN VG", 25: "PT", 26: "IS TR", 27: "FR GR IT MC MR SM", 28: "AL AZ CY DO GT HU LB PL", 29: "BR PS QA UA", 30: "JO KW MU", 31: "MT"}.items() for c in cs.split()}


def _readings(kind: str, text: str) -> list[int]:
    """How many characters of a match to try, in order: for cards and IBANs its whole and its prefixes of whole groups."""
    if kind not in ("card", "iban"):
        return [len(text)]
    ends = [i for i, c in enumerate(text) if c in " -"] + [len(text)]
    if kind == "card":
        return [e for e in ends if sum(map(str.isdigit, text[:e])) >= 13]
    known = IBAN_LENGTHS.get(text[:2])
    return sorted((e for e in ends if e - text[:e].count(" ") >= 15), key=lambda e: (e - text[:e].count(" ") != known, -e))


def _pattern() -> tuple[re.Pattern, list[str]]:
    parts, shift = [], 0
    for name, (p, _) in KINDS.items():
        groups = re.compile(p).groups
        parts.append(f"(?P<{name}>" + re.sub(r"\\([1-9])", lambda m, s=shift: f"\\{int(m[1]) + s + 1}", p) + ")")
        shift += groups + 1
    return re.compile("|".join(parts), re.ASCII), list(KINDS)


class Pseudonymiser:
    def __init__(self, key: bytes):
        self.feistel, (self.pattern, self.kinds) = Feistel(key), _pattern()
        self.value = lru_cache(1 << 16)(lambda kind, text, back: KINDS[kind][1](text, self.feistel, back))
        self.each = {k: re.compile(p, re.ASCII) for k, (p, _) in KINDS.items()}
        self.start = re.compile(r"[0-9@]")

    def _read(self, kind: str, text: str, back: bool) -> tuple[str, int] | None:
        """(new value, characters of text it stands for) of the first reading that is valid."""
        tried = []
        for end in _readings(kind, text):
            if (new := self.value(kind, text[:end], back)) is not None:
                # again until no earlier reading holds, so that the result is read to the same end
                while any(self.value(kind, (new + text[end:])[:e], back) is not None for e in tried):
                    new = self.value(kind, new, back)
                return new, end
            tried.append(end)
        return None

    def __call__(self, text: str | None, back: bool = False) -> tuple[str | None, dict[str, int]]:
        """The text with its pseudonyms (or, with back, the original again), and how many values of each kind."""
        seen = dict.fromkeys(self.kinds, 0)
        if not text or not self.start.search(text):
            return text, seen

        out, done, at = [], 0, 0
        while m := self.pattern.search(text, at):
            at = m.start()
            for kind in self.kinds:
                if (one := self.each[kind].match(text, at)) and (read := self._read(kind, one[0], back)):
                    seen[kind] += 1
                    out += text[done:at], read[0]
                    done = at = at + read[1]
                    break
            else:
                at += 1  # what failed may hide a value that starts later
        return "".join(out) + text[done:], seen


def pseudonymise(docs: DataFrame, key: bytes, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, text, n_<kind>...): each row of docs with the values in its text replaced."""
    out = pa.schema([("doc_id", pa.int64()), ("text", pa.string()), *((f"n_{k}", pa.int64()) for k in KINDS)])

    def run(batches):
        change = Pseudonymiser(key)
        for batch in pieces(batches, "body"):
            texts, counts = zip(*map(change, column(batch, "body")))
            yield batch_of(out, [column(batch, "doc_id"), list(texts), *([c[k] for c in counts] for k in KINDS)])

    ddl = "doc_id long, text string, " + ", ".join(f"n_{k} long" for k in KINDS)
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("body")).mapInArrow(run, ddl)
