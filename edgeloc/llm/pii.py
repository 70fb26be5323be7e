"""PII pseudonyms by a keyed Feistel permutation inside each value's format.

Validated values only: card numbers (Luhn), IBANs (mod 97), social security numbers, phone numbers, IPv4 addresses, dates
that exist, and e-mail addresses. A value is read as an integer of its format's domain, permuted by a balanced
Feistel network with cycle walking, and written in the same format: separators, length, letter case, check digits and
validity stay. A value's pseudonym depends on key, kind and format only, so equal values stay linked across documents. Digits are 0 to 9 only: those of
other scripts are left alone. A card number ends at the first group where it checks, an IBAN at its country's length, whatever groups follow.

Defined results: null text gives null text and no spans; numbers that fail validation stay; rows, and columns besides the text, stay as they are;
an empty table gives an empty one. Dates outside 1900 to 2099 stay. The key is a parameter; the default is for tests.
"""

from __future__ import annotations

import datetime
import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

TEST_KEY = b"not a secret: give a key of your own"

NUMBERS = re.compile(
    r"(?P<iban>\b[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?\b)"
    r"|(?P<date>(?<![\w./-])(?:[0-9]{4}-[0-9]{2}-[0-9]{2}|[0-9]{1,2}/[0-9]{1,2}/[0-9]{4}|[0-9]{1,2}\.[0-9]{1,2}\.[0-9]{4})(?![\w/-]|\.[0-9]))"
    r"|(?P<ip>(?<![\w.])[0-9]{1,3}(?:\.[0-9]{1,3}){3}(?![\w]|\.[0-9]))"
    r"|(?P<ssn>(?<![\w-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![\w-]))"
    r"|(?P<phone>(?<![\w+])\+[0-9]{1,3}[ .-]?(?:\([0-9]{1,4}\)[ .-]?)?[0-9]{2,4}(?:[ .-]?[0-9]{2,4}){1,4}(?!\w)|(?<![\w(])\([0-9]{3}\) ?[0-9]{3}-[0-9]{4}(?!\w))"
    r"|(?P<card>(?<![\w.-])[0-9](?:[ -]?[0-9]){12,18}(?![\w-]|\.[0-9]))"
)
DIGITS = frozenset("0123456789")
#: Lengths of IBANs by country.
IBAN_LENGTHS = {k: int(n) for n, ks in (
    ("15", "NO"), ("16", "BE"), ("18", "DK FI FO GL NL SD"), ("19", "MK SI"), ("20", "AT BA EE KZ LT LU MN XK"), ("21", "CH HR LI LV"),
    ("22", "BG BH CR DE GB GE IE ME RS VA"), ("23", "AE GI IL IQ OM SO TL"), ("24", "AD CZ ES MD PK RO SA SE SK TN VG"), ("25", "LY PT ST"), ("26", "IS TR"),
    ("27", "BI DJ FR GR IT MC MR SM"), ("28", "AL AZ BY CY DO GT HU LB NI PL SV"), ("29", "BR EG PS QA UA"), ("30", "JO KW MU"), ("31", "MT SC"), ("32", "LC"), ("33", "RU"),
) for k in ks.split()}
EMAIL = re.compile(r"[\w.%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_CLASSES = tuple("".join(map(chr, range(a, b + 1))) for a, b in ((48, 57), (97, 122), (65, 90), (0xDF, 0xF6), (0xF8, 0xFF), (0xC0, 0xD6), (0xD8, 0xDE)))
_EARLIEST, _DAYS = datetime.date(1900, 1, 1).toordinal(), datetime.date(2099, 12, 31).toordinal() - datetime.date(1900, 1, 1).toordinal() + 1


class Feistel:
    """A keyed permutation of range(size), for any size."""

    def __init__(self, key: bytes, rounds: int = 8):
        self.key, self.rounds = hashlib.blake2b(key, digest_size=32).digest(), rounds

    def _half(self, value: int, k: int, tweak: bytes, bits: int) -> int:
        n = (bits + 7) // 8
        said = hashlib.blake2b(value.to_bytes(n, "big") + bytes([k]) + tweak, key=self.key, digest_size=min(64, n + 8)).digest()
        return int.from_bytes(said, "big") & ((1 << bits) - 1)

    def _once(self, x: int, bits: int, tweak: bytes, order) -> int:
        left, right = x >> bits, x & ((1 << bits) - 1)
        for k in order:
            left, right = right, left ^ self._half(right, k, tweak, bits)
        return right << bits | left  # halves swapped, so that the reverse order undoes it

    def walk(self, x: int, size: int, tweak: bytes, fits=lambda x: True, back: bool = False) -> int:
        """Permutes until the result is in range and fits."""
        if size < 2:
            return x
        bits = ((size - 1).bit_length() + 1) // 2
        order = range(self.rounds)[::-1] if back else range(self.rounds)
        while True:
            x = self._once(x, bits, tweak, order)
            if x < size and fits(x):
                return x


def luhn(digits: str) -> int:
    """0 if the last digit checks."""
    d = [int(c) for c in reversed(digits)]
    return sum(d[::2] + [sum(divmod(2 * x, 10)) for x in d[1::2]]) % 10


def _refill(value: str, digits: str) -> str:
    """value with its digits replaced in order."""
    new = iter(digits)
    return "".join(next(new) if c in DIGITS else c for c in value)


def _string(f: Feistel, s: str, tweak: bytes, back: bool) -> str:
    """Permutes the characters of known classes, each within its class."""
    x, size, at = 0, 1, []
    for n, c in enumerate(s):
        k = next((k for k in _CLASSES if c in k), None)
        if k:
            x, size = x * len(k) + k.index(c), size * len(k)
            at.append((n, k))
    shape = bytes(next((m for m, k in enumerate(_CLASSES) if c in k), 255) for c in s)
    x, out = f.walk(x, size, tweak + shape, back=back), list(s)
    for n, k in reversed(at):
        x, r = divmod(x, len(k))
        out[n] = k[r]
    return "".join(out)


def _iban_check(country: str, rest: str) -> str:
    return f"{98 - int(''.join(str(int(c, 36)) for c in rest + country + '00')) % 97:02d}"


def pseudonym(f: Feistel, kind: str, value: str, back: bool = False) -> str | None:
    """The pseudonym of a value, or None if it isn't valid; back undoes it."""
    digits = "".join(c for c in value if c in DIGITS)
    if kind == "card":
        if luhn(digits) or not 13 <= len(digits) <= 19 or len(set(digits)) == 1:
            return None
        n = 10 ** (len(digits) - 1)
        cuts = tuple(sum(c in DIGITS for c in value[:e]) for e in _card_ends(value)[:-1])

        def fits(x):  # not of one digit only, and no card ends at a group before the last: it would be read instead
            body = f"{x:0{len(digits) - 1}d}"
            whole = body + str(-luhn(body + "0") % 10)
            return len(set(whole)) > 1 and all(luhn(whole[:c]) or len(set(whole[:c])) == 1 for c in cuts)

        if not fits(int(digits[:-1])):
            return None
        body = f"{f.walk(int(digits[:-1]), n, b'card' + bytes([len(digits), *cuts]), fits, back):0{len(digits) - 1}d}"
        return _refill(value, body + str(-luhn(body + "0") % 10))
    if kind == "ssn":
        ok = lambda x: (x // 10**6) not in (0, 666) and x // 10**6 < 900 and x // 10**4 % 100 and x % 10**4
        return _refill(value, f"{f.walk(int(digits), 10**9, b'ssn', ok, back):09d}") if ok(int(digits)) else None
    if kind == "ip":
        parts = value.split(".")
        if any(int(p) > 255 or (len(p) > 1 and p[0] == "0") for p in parts):
            return None
        x = f.walk(int.from_bytes(bytes(map(int, parts)), "big"), 1 << 32, b"ip", back=back)
        return ".".join(map(str, x.to_bytes(4, "big")))
    if kind == "phone":
        if not 7 <= len(digits) <= 15:
            return None
        country = re.match(r"\+[0-9]{1,3}(?=[ .(-])|", value).group()
        rest = value[len(country) :]
        own = "".join(c for c in rest if c in DIGITS)
        return country + _refill(rest, f"{f.walk(int(own), 10 ** len(own), b'phone%d' % len(own), back=back):0{len(own)}d}")
    if kind == "date":
        sep = next(c for c in value if c not in DIGITS)
        parts = value.split(sep)
        year, month, day = map(int, parts if sep == "-" else parts[::-1])
        if sep == "/" and month > 12:
            month, day, swapped = day, month, True
        else:
            swapped = False
        try:
            x = datetime.date(year, month, day).toordinal() - _EARLIEST
        except ValueError:
            return None
        if not 0 <= x < _DAYS:
            return None
        wide = [len(p) for p in parts]

        def told(x):
            d = datetime.date.fromordinal(x + _EARLIEST)
            if sep == "-":
                return (d.year, d.month, d.day)
            return (d.month, d.day, d.year) if swapped else (d.day, d.month, d.year)

        def fits(x):  # one digit stays one digit, and a form read month first stays so
            t = told(x)
            return all(sep == "-" or w == 4 or len(str(v)) <= w and (w == 2 or v < 10) for v, w in zip(t, wide)) and (not swapped or t[1] > 12)

        x = f.walk(x, _DAYS, b"date%d%d%d" % (ord(sep), swapped, wide[0] * 3 + wide[1]), fits, back)
        return sep.join(f"{v:0{w}d}" for v, w in zip(told(x), wide))
    if kind == "iban":
        bare = value.replace(" ", "")
        if IBAN_LENGTHS.get(bare[:2]) != len(bare) or int("".join(str(int(c, 36)) for c in bare[4:] + bare[:4])) % 97 != 1:
            return None
        rest = _string(f, bare[4:], b"iban" + bare[:2].encode(), back)
        new = iter(bare[:2] + _iban_check(bare[:2], rest) + rest)
        return "".join(c if c == " " else next(new) for c in value)
    local, _, host = value.partition("@")
    return f"{_string(f, local, b'mail', back)}@{host}"


def _card_ends(value: str) -> list[int]:
    """Where a card number of 13 digits or more may end: before a separator, or at the end."""
    return [e for e in range(1, len(value) + 1) if (e == len(value) or value[e] not in DIGITS) and value[e - 1] in DIGITS and sum(c in DIGITS for c in value[:e]) >= 13]


def _readings(kind: str, value: str) -> Iterator[str]:
    """What a candidate may be read as, first choice first: what follows a number in the next group isn't part of it."""
    if kind == "card":
        yield from (value[:e] for e in _card_ends(value))
    elif kind == "iban":
        left = IBAN_LENGTHS.get(value[:2], 99)
        for e, c in enumerate(value, 1):
            left -= c != " "
            if left == 0:
                if e == len(value) or value[e] == " ":
                    yield value[:e]
                return
    else:
        yield value


def replace_pii(text: str, f: Feistel, back: bool = False) -> tuple[str, list[tuple[str, int, int]]]:
    """New text, and (kind, start, end) of what was replaced, in code points of the old text."""
    found = []
    if not DIGITS.isdisjoint(text):
        m = NUMBERS.search(text)
        while m:
            end = m.start() + 1  # a candidate that fails may hide a shorter one behind its first character
            for value in _readings(m.lastgroup, m.group()):
                new = pseudonym(f, m.lastgroup, value, back)
                if new is not None:
                    end = m.start() + len(value)
                    found.append((m.start(), end, m.lastgroup, new))
                    break
            m = NUMBERS.search(text, end)
    if "@" in text:
        for at in re.finditer("@", text):
            start = at.start()
            while start and (text[start - 1].isalnum() or text[start - 1] in "._%+-"):
                start -= 1
            m = EMAIL.match(text, start)
            if m and m.end() > at.end():
                found = [x for x in found if x[1] <= m.start() or x[0] >= m.end()]
                found.append((m.start(), m.end(), "email", pseudonym(f, "email", m.group(), back)))
    out, last = [], 0
    found = sorted(found)
    for start, end, _, new in found:
        if start < last:
            continue
        out += [text[last:start], new]
        last = end
    return "".join(out) + text[last:], [(k, s, e) for s, e, k, _ in found]


def pseudonymise(docs: DataFrame, key: bytes = TEST_KEY, text_col: str = "text", out_col: str = "pii_spans", back: bool = False) -> DataFrame:
    """docs with text_col replaced and an array of (kind, at, until) of what was found in the old text."""
    names, at = [c for c in docs.columns if c != out_col], docs.columns.index(text_col)
    span = T.StructType([T.StructField("kind", T.StringType()), T.StructField("at", T.IntegerType()), T.StructField("until", T.IntegerType())])
    arrow = pa.list_(pa.struct([("kind", pa.string()), ("at", pa.int32()), ("until", pa.int32())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        f = Feistel(key)
        for whole in batches:
            for a in range(0, whole.num_rows, 512):
                b = whole.slice(a, 512)
                done = [(None, []) if t is None else replace_pii(t, f, back) for t in b.column(at).to_pylist()]
                spans = pa.array([[{"kind": k, "at": s, "until": e} for k, s, e in d[1]] for d in done], type=arrow)
                text = pa.array([d[0] for d in done], type=pa.string())
                yield pa.RecordBatch.from_arrays([*(text if c == text_col else b.column(c) for c in names), spans], names=[*names, out_col])

    kind = T.StructType([f if f.name != text_col else T.StructField(f.name, T.StringType()) for f in docs.schema.fields if f.name != out_col] + [T.StructField(out_col, T.ArrayType(span))])
    return docs.mapInArrow(run, kind)


def op9(docs: DataFrame) -> DataFrame:
    """(doc_id, text, n_found, spans): text has the pseudonyms."""
    out = pseudonymise(docs.select("doc_id", F.col("text").cast("string").alias("text")))
    told = F.array_join(F.transform("pii_spans", lambda s: F.concat_ws(":", s["kind"], s["at"], s["until"])), ",")
    return out.select("doc_id", "text", F.size("pii_spans").cast("long").alias("n_found"), told.alias("spans"))
