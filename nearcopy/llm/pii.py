"""Format-preserving pseudonyms for personal data by a keyed Feistel permutation.

Each kind of value has a finite domain: the digits of a phone number, the letters and digits of a mail name, the days
from
1900 to 2099 and so on. A value that is valid for its kind is permuted within the domain by a Feistel network whose
round
function is keyed BLAKE2; where the domain isn't a whole rectangle, the network is walked until it is back in the
domain. So
the result has the same form, is valid again (check digits are made anew), differs between keys, and equal
values get equal pseudonyms in all documents, however they are written.
"""

from __future__ import annotations

import bisect
import datetime
import hashlib
import re
from collections.abc import Callable
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from nearcopy.llm.common import arrow_map, check_columns, claim, documents

#: For trials; production passes its own secret.
TRIAL_KEY = b"pseudonyms of the trial corpus"
ROUNDS = 10


def permute(value: int, low: int, high: int, key: bytes, tweak: bytes) -> int:
    """A keyed permutation of 0 .. low * high - 1 by rounds that add to one half a function of the other."""
    b, a = divmod(value, low)
    for r in range(ROUNDS):
        side, size = (b, low) if r % 2 == 0 else (a, high)
        pad = hashlib.blake2b(b"%d|%b|%d" % (r, tweak, side), key=key[:64], digest_size=32).digest()
        pad = int.from_bytes(pad + hashlib.blake2b(pad, key=key[:64]).digest(), "big") % size
        if r % 2 == 0:
            a = (a + pad) % low
        else:
            b = (b + pad) % high
    return b * low + a


def permute_below(
    value: int, size: int, key: bytes, tweak: bytes, allowed: Callable[[int], bool] = lambda v: True
) -> int:
    """A keyed permutation of the allowed values below `size`."""
    low = max(1, int(size**0.5))
    high = -(-size // low)
    while True:
        value = permute(value, low, high, key, tweak)
        if value < size and allowed(value):
            return value


def permute_symbols(text: str, alphabets: list[str], key: bytes, tweak: bytes) -> str:
    """text[i] is in alphabets[i]; so is the result's."""
    if not text:
        return text
    half = len(text) // 2
    sizes = [1, 1]
    value = 0
    for i, (c, letters) in enumerate(zip(text, alphabets, strict=True)):
        value = value * len(letters) + letters.index(c)
        sizes[i >= half] *= len(letters)
    high, low = sizes
    value = permute(value, low, high, key, tweak + b"|" + ",".join(str(len(a)) for a in alphabets).encode())
    out = []
    for letters in reversed(alphabets):
        value, digit = divmod(value, len(letters))
        out.append(letters[digit])
    return "".join(reversed(out))


DIGITS, LOWER, UPPER, HEX = "0123456789", "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789abcdef"


def _put_back(pattern: str, symbols: str, takes: Callable[[str], bool]) -> str:
    it = iter(symbols)
    return "".join(next(it) if takes(c) else c for c in pattern)


def luhn_digit(body: str) -> str:
    total = 0
    for i, c in enumerate(reversed(body)):
        d = int(c) * (2 if i % 2 == 0 else 1)
        total += d - 9 * (d > 9)
    return str(-total % 10)


def _card(text: str, key: bytes) -> str | None:
    digits = re.sub(r"\D", "", text)
    if not 13 <= len(digits) <= 19 or luhn_digit(digits[:-1]) != digits[-1] or len(set(digits)) == 1:
        return None
    body = permute_symbols(digits[:-1], [DIGITS] * (len(digits) - 1), key, b"card")
    return _put_back(text, body + luhn_digit(body), str.isdigit)


def _iban_digits(country: str, account: str) -> str:
    number = "".join(str(int(c, 36)) for c in account + country + "00")
    return f"{98 - int(number) % 97:02d}"


def _iban(text: str, key: bytes) -> str | None:
    plain = text.replace(" ", "")
    if not 15 <= len(plain) <= 34 or _iban_digits(plain[:2], plain[4:]) != plain[2:4]:
        return None
    account = permute_symbols(
        plain[4:], [DIGITS if c in DIGITS else UPPER for c in plain[4:]], key, b"iban" + plain[:2].encode()
    )
    return _put_back(text, plain[:2] + _iban_digits(plain[:2], account) + account, lambda c: c != " ")


def _phone(text: str, key: bytes) -> str | None:
    m = re.match(r"\+\d{1,3}(?=[ .(-])|", text)
    head, rest = text[: m.end()], text[m.end() :]
    digits = re.sub(r"\D", "", rest)
    if not 7 <= len(digits) <= 12:
        return None
    return head + _put_back(rest, permute_symbols(digits, [DIGITS] * len(digits), key, b"phone"), str.isdigit)


def _social(text: str, key: bytes) -> str | None:
    def fits(v: int) -> bool:
        area, group, serial = v // 1_000_000, v // 10_000 % 100, v % 10_000
        return area not in (0, 666) and area < 900 and group > 0 and serial > 0

    value = int(text.replace("-", ""))
    if not fits(value):
        return None
    new = f"{permute_below(value, 900_000_000, key, b'social', fits):09d}"
    return f"{new[:3]}-{new[3:5]}-{new[5:]}"


def _address(text: str, key: bytes) -> str | None:
    parts = [int(p) for p in text.split(".")]
    if len(parts) != 4 or max(parts) > 255 or any(len(p) > 1 and p[0] == "0" for p in text.split(".")):
        return None
    value = permute(int.from_bytes(bytes(parts)), 1 << 16, 1 << 16, key, b"address")
    return ".".join(map(str, value.to_bytes(4)))


def _mail(text: str, key: bytes) -> str | None:
    name, _, domain = text.rpartition("@")
    sort = [DIGITS if c in DIGITS else LOWER if c in LOWER else UPPER if c in UPPER else None for c in name]
    symbols = "".join(c for c, s in zip(name, sort, strict=True) if s)
    if not symbols or "." not in domain:
        return None
    new = permute_symbols(symbols, [s for s in sort if s], key, b"mail")
    return _put_back(name, new, lambda c: c in DIGITS or c in LOWER or c in UPPER) + "@" + domain


def _secret(text: str, key: bytes) -> str | None:
    if not (
        any(c.isdigit() for c in text) and any(c.isalpha() for c in text)
    ) or text != text.lower() and text != text.upper():
        return None
    new = permute_symbols(text.lower(), [HEX] * len(text), key, b"secret")
    return new if text == text.lower() else new.upper()


_FIRST_DAY = datetime.date(1900, 1, 1).toordinal()
_DAYS = datetime.date(2100, 1, 1).toordinal() - _FIRST_DAY
#: Orders of the parts that are tried, by whether the year comes first.
_ORDERS = {True: ["ymd"], False: ["dmy", "mdy"]}


def _date(text: str, key: bytes) -> str | None:
    parts, sign = re.split(r"[-/.]", text), re.search(r"[-/.]", text)[0]
    for order in _ORDERS[len(parts[0]) == 4]:
        at = {p: int(x) for p, x in zip(order, parts, strict=True)}
        try:
            day = datetime.date(at["y"], at["m"], at["d"]).toordinal() - _FIRST_DAY
        except ValueError:
            continue
        if 0 <= day < _DAYS:
            new = datetime.date.fromordinal(permute_below(day, _DAYS, key, b"date") + _FIRST_DAY)
            return sign.join(
                f"{new.year:04d}" if p == "y" else f"{getattr(new, {'m': 'month', 'd': 'day'}[p]):02d}" for p in order
            )
    return None


_KINDS: dict[str, tuple[str, Callable[[str, bytes], str | None]]] = {
    "mail": (r"(?<![\w.+-])[A-Za-z0-9][A-Za-z0-9._%+-]*@[A-Za-z0-9](?:[A-Za-z0-9-]*\.)+[A-Za-z]{2,}", _mail),
    "iban": (r"(?<!\w)[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?(?!\w)", _iban),
    "secret": (r"(?<!\w)(?:[0-9a-f]{32,128}|[0-9A-F]{32,128})(?!\w)", _secret),
    "address": (r"(?<![\w.])\d{1,3}(?:\.\d{1,3}){3}(?!\w|\.\d)", _address),
    "date": (r"(?<![\w.])(?:\d{4}([-/.])\d{2}\1\d{2}|\d{2}([-/.])\d{2}\2\d{4})(?![\w]|[-/.]\d)", _date),
    "social": (r"(?<![\w-])\d{3}-\d{2}-\d{4}(?![\w-])", _social),
    "phone": (
        r"(?<!\w)(?:\+\d{1,3}[ .-]?)?\(\d{2,4}\)[ .-]?\d{3,4}[ .-]?\d{3,4}(?!\w)|(?<!\w)\+\d{1,3}[ .-]\d{2,4}[ .-]\d{3,4}(?:[ .-]\d{2,4}){0,2}(?!\w)|(?<![\w-])\d{3}[-.]\d{3}[-.]\d{4}(?![\w-])",
        _phone,
    ),
    "card": (r"(?<![\w])\d(?:[ -]?\d){12,18}(?!\w)", _card),
}
_all = {k: re.compile(p) for k, (p, _) in _KINDS.items()}
_digit = re.compile(r"[0-9]")


def pseudonymise(text: str | None, key: bytes = TRIAL_KEY) -> tuple[str | None, dict[str, int]]:
    """The text with its valid values replaced, and how many of each kind. Values of an earlier kind aren't looked at
    again."""
    if not text or ("@" not in text and not _digit.search(text)):
        return text, {}
    found: list[tuple[int, int, str, str]] = []
    for kind, pattern in _all.items():
        if kind == "mail" and "@" not in text:
            continue
        for m in pattern.finditer(text):
            at = bisect.bisect(found, (m.end(),))
            if at and found[at - 1][1] > m.start():
                continue  # it overlaps an earlier kind's value
            if (new := _cached(kind, m.group(), key)) is not None:
                found.insert(at, (m.start(), m.end(), kind, new))
    if not found:
        return text, {}
    out, at, counts = [], 0, {}
    for a, e, kind, new in found:
        out += [text[at:a], new]
        at = e
        counts[kind] = counts.get(kind, 0) + 1
    return "".join([*out, text[at:]]), counts


@lru_cache(maxsize=20_000)
def _cached(kind: str, value: str, key: bytes) -> str | None:
    return _KINDS[kind][1](value, key)


def add_pseudonyms(docs: DataFrame, text: str = "text", key: bytes = TRIAL_KEY, count: str = "n_values") -> DataFrame:
    """`docs` with the text's personal data replaced, and a column with the number of replaced values.

    Null stays null and empty stays empty, with 0 values. Numbers and dates that aren't valid stay. Whole texts of
    any length
    are read. A column named as `count` is replaced.
    """
    check_columns(docs, text)
    from pyspark.sql.types import LongType, StructType

    docs = docs.drop(count)
    place, names = docs.columns.index(text), [*docs.columns, count]

    def run(batches):
        claim("pii", _cached.cache_clear)
        for b in batches:
            texts, counts = [], []
            for t in b.column(place).to_pylist():
                new, found = pseudonymise(t, key)
                texts.append(new)
                counts.append(sum(found.values()))
            columns = list(b.columns)
            columns[place] = pa.array(texts, pa.string())
            yield pa.RecordBatch.from_arrays([*columns, pa.array(counts, pa.int64())], names=names)

    return docs.transform(arrow_map, run, StructType([*docs.schema.fields]).add(count, LongType()))


def op2_pii_pseudonyms(spark: SparkSession, sf_dir: str) -> DataFrame:
    return add_pseudonyms(documents(spark, sf_dir).select("doc_id", "text"))
