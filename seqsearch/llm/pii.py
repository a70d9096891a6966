"""Format-preserving pseudonyms for personal numbers and dates.

A value that passes its check (card and account check digits, calendar, octets, area codes) is replaced by another valid
value of the same format: its number is sent through a keyed Feistel network over exactly the numbers of that format, a
permutation, so equal values get equal pseudonyms in all documents, different values different ones, and the holder of the
key can go back.  Separators and letter case stay where they were.
"""

from __future__ import annotations

import datetime
import hashlib
import re
from collections.abc import Callable, Iterator
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import text_function

KINDS = ("card", "phone", "ip", "ssn", "iban", "date", "email", "secret")
ROUNDS = 8
_FIRST, _LAST = datetime.date(1900, 1, 1).toordinal(), datetime.date(2099, 12, 31).toordinal()

_SHAPES = {
    "date": r"[0-9]{4}-[0-9]{2}-[0-9]{2}(?!-?[0-9])|[0-9]{4}/[0-9]{1,2}/[0-9]{1,2}|[0-9]{1,2}\.[0-9]{1,2}\.[0-9]{4}|[0-9]{1,2}/[0-9]{1,2}/[0-9]{4}",
    "ssn": r"[0-9]{3}-[0-9]{2}-[0-9]{4}",
    "ip": r"[0-9]{1,3}(?:\.[0-9]{1,3}){3}(?!\.[0-9])",
    "phone": r"\+[0-9]{1,3}[ .-]?\(0\)[ .-]?[0-9]{2,4}(?:[ .-]?[0-9]{2,4}){2,3}|\+[0-9]{1,3}[ .-]?\([0-9]{2,4}\)[ .-]?[0-9]{3,4}[ .-]?[0-9]{3,4}|\+[0-9]{1,3}(?:[ .-][0-9]{2,4}){3,4}|\+[0-9]{9,15}"
    r"|\([0-9]{3}\)[ ]?[0-9]{3}[.-][0-9]{4}|[0-9]{3}[.-][0-9]{3}[.-][0-9]{4}",
    "card": r"[0-9]{13,19}|[0-9]{4}(?P<four>[ -])[0-9]{4}(?P=four)[0-9]{4}(?P=four)[0-9]{1,7}|[0-9]{4}(?P<six>[ -])[0-9]{6}(?P=six)[0-9]{5}",
    "iban": r"[A-Z]{2}[0-9]{2}(?:[ ]?[A-Z0-9]{4}){2,7}(?:[ ]?[A-Z0-9]{1,3})?",
}
_AFTER = r"(?:(?![\w/-])|(?<=[0-9]{4}-[0-9]{2}-[0-9]{2})(?=[Tt][0-9]{2}))"  # a date may be followed by its time
_STOP = {k: re.compile(_AFTER if k != "iban" else r"(?!\w)") for k in _SHAPES}
_SHAPE = {k: re.compile(v) for k, v in _SHAPES.items()}
_ENDED = {k: re.compile(f"(?:{v}){_STOP[k].pattern}") for k, v in _SHAPES.items()}
_NUMBERS = re.compile(r"(?<![\w.+/-])(?:" + "|".join(f"(?P<{k}>{v})" for k, v in _SHAPES.items() if k != "iban") + ")" + _AFTER)
_IBAN = re.compile(rf"(?<!\w)(?P<iban>{_SHAPES['iban']})(?!\w)")
#: Fixed: the country calling codes of two digits; 1 and 7 have one digit, all others three.
_CODES = frozenset(
    "20 27 30 31 32 33 34 36 39 40 41 43 44 45 46 47 48 49 51 52 53 54 55 56 57 58 60 61 62 63 64 65 66 81 82 84 86 90 91 92 93 94 95 98".split()
)
#: Length of the account numbers of a country, where it is fixed.
_IBAN_LENGTH = {
    "AD": 24, "AE": 23, "AT": 20, "BE": 16, "BG": 22, "CH": 21, "CY": 28, "CZ": 24, "DE": 22, "DK": 18, "EE": 20, "ES": 24, "FI": 18, "FR": 27,
    "GB": 22, "GR": 27, "HR": 21, "HU": 28, "IE": 22, "IS": 26, "IT": 27, "LI": 21, "LT": 20, "LU": 20, "LV": 21, "MC": 27, "MT": 31, "NL": 18,
    "NO": 15, "PL": 28, "PT": 25, "RO": 24, "SA": 24, "SE": 24, "SI": 19, "SK": 24, "SM": 27, "TR": 26,
}
_EMAIL = re.compile(r"(?<![\w.+-])([A-Za-z0-9][\w.+-]{0,63})@((?:[A-Za-z0-9-]{1,63}\.){1,8}[A-Za-z]{2,24})(?![\w-])", re.A)
# Without re.A the letters K and S would also stand for the Kelvin sign and the long s, which no permutation of ours holds.
_SECRET = re.compile(r"(?<!\w)(?:(AKIA)([0-9A-Z]{16})|((?:password|passwd|token|secret|api_?key)\s{0,3}[=:]\s{0,3}[\"']?)([0-9A-Za-z_+/-]{12,}))(?!\w)", re.I | re.A)
_DIGIT = re.compile(r"\d", re.A)


# --- the permutation ------------------------------------------------------------------------------------------------
def _round(key: bytes, tweak: bytes, i: int, half: int) -> int:
    data = b"%d|%b|%d" % (i, tweak, half)
    return int.from_bytes(hashlib.blake2b(data, key=key, digest_size=32).digest(), "big")


def _network(x: int, left: int, right: int, key: bytes, tweak: bytes, back: bool) -> int:
    """Feistel on left + right bits; even rounds change the left half, odd ones the right."""
    a, b = x >> right, x & ((1 << right) - 1)
    for i in reversed(range(ROUNDS)) if back else range(ROUNDS):
        if i % 2 == 0:
            a ^= _round(key, tweak, i, b) & ((1 << left) - 1)
        else:
            b ^= _round(key, tweak, i, a) & ((1 << right) - 1)
    return a << right | b


def permute(x: int, size: int, key: bytes, tweak: bytes, back: bool = False) -> int:
    """A keyed permutation of 0..size-1: the network over the next power of two, walked until the value is in range."""
    if not 0 <= x < max(size, 1):  # the walk from outside may never come back
        raise ValueError(f"{x} is not below {size}")
    if size < 2:
        return x
    bits = max(2, (size - 1).bit_length())
    right = bits // 2
    while True:
        x = _network(x, bits - right, right, key, tweak, back)
        if x < size:
            return x


def _mixed(chars: str, key: bytes, tweak: bytes, back: bool) -> str:
    """Permute ASCII digits as digits and ASCII letters as letters of the same case; other characters stay.

    The permuted number doesn't depend on case: equal letters stay linked in either.
    """
    sizes = [1 if not c.isascii() else 10 if c.isdigit() else 26 if c.isalpha() else 1 for c in chars]
    value, size = 0, 1
    for c, n in zip(chars, sizes, strict=True):
        value = value * n + (0 if n == 1 else int(c) if n == 10 else ord(c) - (65 if c.isupper() else 97))
        size *= n
    value, out = permute(value, size, key, tweak, back), []
    for c, n in zip(reversed(chars), reversed(sizes), strict=True):
        value, d = divmod(value, n)
        out.append(c if n == 1 else str(d) if n == 10 else chr(d + (65 if c.isupper() else 97)))
    return "".join(reversed(out))


def _digits(text: str) -> str:
    return "".join(_DIGIT.findall(text))


def _filled(form: str, digits: str) -> str:
    """``form`` with its digits replaced in order."""
    it = iter(digits)
    return _DIGIT.sub(lambda _: next(it), form)


# --- checks and pseudonyms, kind by kind: each returns None if the value fails its check -----------------------------
def luhn(digits: str) -> int:
    """0 if the check digit is right."""
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = int(c) * (1 + i % 2)
        total += d - 9 * (d > 9)
    return total % 10


def _card(text: str, key: bytes, back: bool) -> str | None:
    d = _digits(text)
    if not 13 <= len(d) <= 19 or d[0] not in "23456" or luhn(d) or len(set(d)) == 1:
        return None
    body = f"{permute(int(d[1:-1]), 10 ** (len(d) - 2), key, b'card%d' % len(d), back):0{len(d) - 2}d}"
    body = d[0] + body
    return _filled(text, body + str(-luhn(body + "0") % 10))


def _phone(text: str, key: bytes, back: bool) -> str | None:
    """The country code and the first digit after it stay, what follows is permuted: the same number in any grouping, and
    with or without a bracketed trunk zero, gets the same digits.  A number without a plus has ten digits and country code 1."""
    form = text.replace("(0)", "()")
    d = _digits(form)
    if not 9 <= len(d) <= 15:
        return None
    code = ""
    if text[0] == "+":
        code = d[: 1 if d[0] in "17" else 2 if d[:2] in _CODES else 3]
    first, tail = d[len(code)], d[len(code) + 1 :]
    new = permute(int(tail), 10 ** len(tail), key, f"phone{code or 1} {first} {len(tail)}".encode(), back)
    return _filled(form, f"{code}{first}{new:0{len(tail)}d}").replace("()", "(0)")


def _ip(text: str, key: bytes, back: bool) -> str | None:
    parts = text.split(".")
    if any(int(p) > 255 or (len(p) > 1 and p[0] == "0") for p in parts):
        return None
    value = int.from_bytes(bytes(map(int, parts)), "big")
    return ".".join(map(str, permute(value, 1 << 32, key, b"ip", back).to_bytes(4, "big")))


def _ssn(text: str, key: bytes, back: bool) -> str | None:
    a, g, s = map(int, text.split("-"))
    if a in (0, 666) or a >= 900 or g == 0 or s == 0:
        return None
    area = a - 1 - (a > 666)  # 898 areas, 99 groups, 9999 serials
    value = permute((area * 99 + g - 1) * 9999 + s - 1, 898 * 99 * 9999, key, b"ssn", back)
    value, s = divmod(value, 9999)
    area, g = divmod(value, 99)
    return f"{area + 1 + (area >= 665):03d}-{g + 1:02d}-{s + 1:04d}"


def _iban(text: str, key: bytes, back: bool) -> str | None:
    flat = text.replace(" ", "")

    def rest(country: str, check: str, account: str) -> int:
        return int("".join(str(int(c, 36)) for c in account + country + check)) % 97

    if not 15 <= len(flat) <= 34 or rest(flat[:2], flat[2:4], flat[4:]) != 1:
        return None
    account = _mixed(flat[4:], key, b"iban" + flat[:2].encode(), back)
    new = iter(flat[:2] + f"{98 - rest(flat[:2], '00', account):02d}" + account)
    return "".join(c if c == " " else next(new) for c in text)


def _date(text: str, key: bytes, back: bool) -> str | None:
    separator = next(c for c in text if not c.isdigit())
    parts = text.split(separator)
    year_first = len(parts[0]) == 4
    y, m, d = map(int, parts if year_first else reversed(parts))
    month_first = False
    if not year_first and separator == "/" and m > 12 >= d:
        m, d, month_first = d, m, True
    try:
        day = datetime.date(y, m, d).toordinal()
    except ValueError:
        return None
    if not _FIRST <= day <= _LAST:
        return None
    new = datetime.date.fromordinal(_FIRST + permute(day - _FIRST, _LAST - _FIRST + 1, key, b"date", back))
    month_first = month_first and new.day > 12  # else it would be read day first, as another date
    padded = year_first and separator == "-" or all(len(p) >= 2 for p in parts)
    shown = [str(new.month).zfill(2 if padded else 1), str(new.day).zfill(2 if padded else 1)]
    if not year_first and not month_first:
        shown.reverse()
    return separator.join([str(new.year), *shown] if year_first else [*shown, str(new.year)])


_OF_KIND: dict[str, Callable[[str, bytes, bool], str | None]] = {"card": _card, "phone": _phone, "ip": _ip, "ssn": _ssn, "date": _date, "iban": _iban}


def pseudonym(kind: str, value: str, key: bytes, back: bool = False) -> str | None:
    """The pseudonym of a value, or (``back``) the value of a pseudonym; None if it fails the kind's check.

    All forms of a date share one permutation.  Dates written with slashes are day first unless that is no date; the pseudonym
    of a month-first one keeps that order where it can be read, and is written day first where not, so its way back is the
    same date, perhaps day first.
    """
    if kind == "email":
        local, _, domain = value.partition("@")
        return f"{_mixed(local, key, b'email' + domain.lower().encode(), back)}@{domain}"
    if kind == "secret":  # a round has 256 bits: longer secrets go piece by piece
        if len(value) <= 96:
            return _mixed(value, key, b"secret", back)
        return "".join(_mixed(value[i : i + 64], key, b"secret%d" % i, back) for i in range(0, len(value), 64))
    return _OF_KIND[kind](value, key, back)


# --- texts ----------------------------------------------------------------------------------------------------------
def _spans(text: str, start: int, kinds: tuple[str, ...]) -> Iterator[tuple[int, int, str]]:
    """All spans from ``start`` that have the shape of a kind; longer ones first, but account numbers of their country's length."""
    for kind in kinds:
        m = _ENDED[kind].match(text, start)
        if m:
            stops = [m.end(), *(p for p in range(m.end() - 1, start, -1) if text[p] == " " and _STOP[kind].match(text, p) and _SHAPE[kind].fullmatch(text, start, p))]
            if kind == "iban":
                stops.sort(key=lambda p: len(text[start:p].replace(" ", "")) != _IBAN_LENGTH.get(text[start : start + 2]))
            yield from ((start, p, kind) for p in stops)


def _scan(text: str, pattern: re.Pattern, kinds: tuple[str, ...], valid: Callable[[str, str], bool]) -> Iterator[tuple[int, int, str]]:
    """Valid values from left to right; where a candidate fails, the next may start inside it."""
    at = 0
    while m := pattern.search(text, at):
        order = (m.lastgroup, *(k for k in kinds if k != m.lastgroup))
        span = next((x for x in _spans(text, m.start(), order) if valid(x[2], text[x[0] : x[1]])), None)
        at = span[1] if span else m.start() + 1
        if span:
            yield span


def find(text: str, valid: Callable[[str, str], bool] = lambda kind, value: pseudonym(kind, value, b"") is not None) -> list[tuple[int, int, str]]:
    """(start, stop, kind) of the values that pass their checks, in order, without overlaps."""
    found: list[tuple[int, int, str]] = []
    if _DIGIT.search(text):
        found += _scan(text, _NUMBERS, tuple(k for k in _SHAPES if k != "iban"), valid)
        found += _scan(text, _IBAN, ("iban",), valid)
        for m in _SECRET.finditer(text):
            k = 2 if m[2] else 4
            if _DIGIT.search(m[k]):
                found.append((m.start(k), m.end(k), "secret"))
    if "@" in text:
        found += [(m.start(), m.end(), "email") for m in _EMAIL.finditer(text)]
    found.sort(key=lambda x: (x[0], -x[1]))
    out, until = [], 0
    for x in found:
        if x[0] >= until:
            out.append(x)
            until = x[1]
    return out


def replace(text: str | None, key: bytes, kinds: tuple[str, ...] = KINDS, back: bool = False) -> tuple[str | None, list[tuple[int, int, str]]]:
    """The text with pseudonyms, and (start, stop, kind) of each in the text given.  Null stays null.

    The spans tell the way back where a pseudonym and digits beside it happen to pass the check of a longer value.
    """
    if not text:
        return text, []
    one = lru_cache(4096)(lambda kind, value: pseudonym(kind, value, key, back))
    parts, spans, at = [], [], 0
    for start, stop, kind in find(text, lambda kind, value: one(kind, value) is not None):
        new = one(kind, text[start:stop]) if kind in kinds else None
        if new is not None:
            parts += [text[at:start], new]
            spans.append((start, stop, kind))
            at = stop
    return ("".join([*parts, text[at:]]) if spans else text), spans


def pseudonymise(docs: DataFrame, key: bytes, doc_id: str = "doc_id", text: str = "text", kinds: tuple[str, ...] = KINDS) -> DataFrame:
    """(doc_id, text, n_replaced, spans): whole texts with pseudonyms, one row for each row; null texts stay null.

    ``key`` has 1 to 64 bytes; whoever holds it can go back.  Other columns of ``docs`` are not read.
    """

    def of(texts: list[str | None]) -> pa.Array:
        found = [replace(t, key, kinds) for t in texts]
        spans = pa.array([[{"start": a, "stop": b, "kind": k} for a, b, k in f[1]] for f in found], pa.list_(pa.struct([("start", pa.int32()), ("stop", pa.int32()), ("kind", pa.string())])))
        return pa.StructArray.from_arrays([pa.array([f[0] for f in found], pa.string()), pa.array([len(f[1]) for f in found], pa.int32()), spans], names=["text", "n_replaced", "spans"])

    done = text_function(of, "struct<text:string,n_replaced:int,spans:array<struct<start:int,stop:int,kind:string>>>")
    own = docs.select(F.col(doc_id).alias("doc_id"), done(F.col(text)).alias("r"))
    return own.select("doc_id", "r.text", "r.n_replaced", "r.spans")


def with_pseudonyms(docs: DataFrame, key: bytes, text: str = "text", kinds: tuple[str, ...] = KINDS) -> DataFrame:
    """``docs``, all columns, with pseudonyms in the text, one row for each row in any order; null and empty texts, and repeated
    rows, stay as they are.  No other column is read, so their names and nulls don't matter."""
    done = text_function(lambda texts: [replace(t, key, kinds)[0] for t in texts], "string")
    return docs.withColumn(text, done(F.col(text)))
