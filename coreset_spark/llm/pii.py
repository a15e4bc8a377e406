"""Format-preserving pseudonyms for validated numbers, dates and addresses, by keyed Feistel permutations.

A value that is recognised and valid (card numbers by their check digit, IBANs by theirs, real
dates, IPv4 octets, assignable phone and social security numbers) is permuted, under a key, among
the valid values of its format: the result has the same separators and lengths, is valid again,
and equal values get equal pseudonyms in every document, without any table of pairs to join. With
the key the permutation can be undone (:func:`unveil`).

One pass of Arrow batches over whole texts; nothing is shuffled. Only tokens around a digit, an
at sign or a key prefix are looked at, so the cost follows the text's length.

Defined results: null stays null; an empty text stays empty; rows with equal doc_id are treated
each by itself; a value that fails its check stays as it is; overlapping candidates go to the
first that starts, by the order of the kinds; an empty table gives an empty one; only doc_id and
text are read.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from datetime import date, timedelta
from functools import lru_cache
from math import isqrt

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

ROUNDS = 8


@dataclass(frozen=True)
class Feistel:
    """A keyed permutation of 0 .. size - 1; each kind of value has its own."""

    key: bytes
    kind: str
    size: int

    def _f(self, turn: int, half: int, of: int) -> int:
        data = f"{self.kind}|{self.size}|{turn}|{half}".encode()
        return int.from_bytes(hashlib.blake2b(data, key=self.key, digest_size=16).digest()) % of

    def _walk(self, x: int, back: bool) -> int:
        if self.size < 2:
            return x
        b = isqrt(self.size - 1) + 1
        a = -(-self.size // b)
        while True:  # over the few numbers beyond the format, until one is in it
            left, right = divmod(x, b)
            for turn in range(ROUNDS - 1, -1, -1) if back else range(ROUNDS):
                sign = -1 if back else 1
                if turn % 2:
                    right = (right + sign * self._f(turn, left, b)) % b
                else:
                    left = (left + sign * self._f(turn, right, a)) % a
            x = left * b + right
            if x < self.size:
                return x

    def __call__(self, x: int, back: bool = False) -> int:
        return self._walk(x, back)


def _refill(shape: str, chars: str, wanted: Callable[[str], bool]) -> str:
    """The shape with its wanted characters replaced in order."""
    it = iter(chars)
    return "".join(next(it) if wanted(c) else c for c in shape)


def _digit(c: str) -> bool:
    return "0" <= c <= "9"


def _digits(s: str) -> str:
    return "".join(filter(_digit, s))


def luhn(digits: str) -> int:
    """The check digit that completes the digits."""
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = int(c) * (2 if i % 2 == 0 else 1)
        total += d - 9 if d > 9 else d
    return -total % 10


def _card(s: str, key: bytes, back: bool) -> str | None:
    d = _digits(s)
    if not 13 <= len(d) <= 19 or luhn(d[:-1]) != int(d[-1]) or len(set(d)) == 1:
        return None
    n = len(d) - 2  # the first digit names the scheme and stays
    new = d[0] + str(Feistel(key, f"card{d[0]}", 10**n)(int(d[1:-1]), back)).zfill(n)
    return _refill(s, new + str(luhn(new)), _digit)


def _ip(s: str, key: bytes, back: bool) -> str | None:
    parts = s.split(".")
    if any(int(p) > 255 or (len(p) > 1 and p[0] == "0") for p in parts):
        return None
    x = Feistel(key, "ipv4", 2**32)(int.from_bytes(bytes(map(int, parts))), back)
    return ".".join(map(str, x.to_bytes(4)))


def _phone(s: str, key: bytes, back: bool) -> str | None:
    d = _digits(s)
    national = len(d) == 10 and s[0] != "+" or len(d) == 11 and d[0] == "1"
    if national:
        head, rest = d[:-10], d[-10:]
        national = rest[0] in "23456789" and rest[3] in "23456789"
    if national:
        x = ((int(rest[0]) - 2) * 100 + int(rest[1:3])) * 8 + int(rest[3]) - 2
        x = Feistel(key, "phone1", 8 * 100 * 8 * 10**6)(x * 10**6 + int(rest[4:]), back)
        x, tail = divmod(x, 10**6)
        x, exchange = divmod(x, 8)
        area, two = divmod(x, 100)
        return _refill(s, f"{head}{area + 2}{two:02d}{exchange + 2}{tail:06d}", _digit)
    if s[0] != "+" or not 8 <= len(d) <= 15:
        return None
    c = 1 if d[0] == "1" else 3  # the country stays
    n = len(d) - c
    x = int(d[c:])
    while True:  # a number that cannot be assigned never becomes one that can, so that both can be told again
        x = Feistel(key, f"phone+{d[:c]}", 10**n)(x, back)
        rest = str(x).zfill(n)
        if c == 3 or n != 10 or not (rest[0] in "23456789" and rest[3] in "23456789"):
            return _refill(s, d[:c] + rest, _digit)


def _ssn(s: str, key: bytes, back: bool) -> str | None:
    a, g, n = int(s[:3]), int(s[4:6]), int(s[7:])
    areas = [x for x in range(1, 900) if x != 666]
    if a not in (0, 666) and a < 900 and g and n:
        x = (areas.index(a) * 99 + g - 1) * 9999 + n - 1
        x, n = divmod(Feistel(key, "ssn", len(areas) * 99 * 9999)(x, back), 9999)
        a, g = divmod(x, 99)
        return f"{areas[a]:03d}-{g + 1:02d}-{n + 1:04d}"
    return None


FIRST_DAY, DAYS = date(1900, 1, 1), 73_049  # to the end of 2099


def _date(s: str, key: bytes, back: bool) -> str | None:
    p = list(map(int, re.split(r"\D", s)))
    if s[4] in "-/.":
        order = (0, 1, 2)
    elif "/" in s and p[0] <= 12:
        order = (2, 0, 1)
    else:
        order = (2, 1, 0)
    try:
        day = (date(p[order[0]], p[order[1]], p[order[2]]) - FIRST_DAY).days
    except ValueError:
        return None
    if not 0 <= day < DAYS:
        return None
    told = "/" in s and order == (2, 1, 0)  # day first, told by a day above 12: so is its pseudonym
    while True:
        day = Feistel(key, "date", DAYS)(day, back)
        new = FIRST_DAY + timedelta(day)
        if not told or new.day > 12:
            break
    values = {order[0]: f"{new.year:04d}", order[1]: f"{new.month:02d}", order[2]: f"{new.day:02d}"}
    return _refill(s if len(_digits(s)) == 8 else re.sub(r"\d+", lambda m: m[0].zfill(2), s), "".join(values[i] for i in range(3)), _digit)


def _shaped(s: str, key: bytes, back: bool, kind: str) -> str:
    """Letters and digits permuted together, each within its own kind and case."""
    radix = [26 if c.islower() else 26 if c.isupper() else 10 if _digit(c) else 1 for c in s]
    base = [ord("a") if c.islower() else ord("A") if c.isupper() else ord("0") if _digit(c) else ord(c) for c in s]
    x, size = 0, 1
    for c, r, b in zip(s, radix, base, strict=True):
        x, size = x * r + (ord(c) - b if r > 1 else 0), size * r
    shape = "".join("a" if c.islower() else "A" if c.isupper() else "0" if _digit(c) else c for c in s)
    x = Feistel(key, f"{kind}{shape}", size)(x, back)
    out = []
    for r, b in zip(reversed(radix), reversed(base), strict=True):
        x, d = divmod(x, r)
        out.append(chr(b + d))
    return "".join(reversed(out))


def _email(s: str, key: bytes, back: bool) -> str | None:
    local, _, domain = s.rpartition("@")
    name, _, top = domain.rpartition(".")
    return f"{_shaped(local, key, back, 'local')}@{_shaped(name, key, back, 'domain')}.{top}"


def _iban(s: str, key: bytes, back: bool) -> str | None:
    bare = s.replace(" ", "")
    number = lambda x: int("".join(str(int(c, 36)) for c in x))
    if not 15 <= len(bare) <= 34 or number(bare[4:] + bare[:4]) % 97 != 1:
        return None
    rest = _shaped(bare[4:], key, back, f"iban{bare[:2]}")
    new = f"{bare[:2]}{98 - number(rest + bare[:2] + '00') % 97:02d}{rest}"
    return _refill(s, new, lambda c: c != " ")


def _secret(s: str, key: bytes, back: bool) -> str | None:
    if re.fullmatch(r"[0-9A-F]+", s):
        return _secret(s.lower(), key, back).upper()
    if re.fullmatch(r"[0-9a-f]+", s):
        return f"{Feistel(key, f'hex{len(s)}', 16 ** len(s))(int(s, 16), back):0{len(s)}x}"
    return s[:4] + _shaped(s[4:], key, back, "key")


#: Kinds in the order in which they are tried at a place: name, pattern, permutation.
KINDS: tuple[tuple[str, str, Callable[[str, bytes, bool], str | None]], ...] = (
    ("email", r"[A-Za-z0-9][A-Za-z0-9._%+-]{0,63}@[A-Za-z0-9](?:[A-Za-z0-9.-]{0,200}[A-Za-z0-9])?\.[A-Za-z]{2,24}(?![A-Za-z0-9])", _email),
    ("iban", r"[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?(?![A-Za-z0-9])", _iban),
    ("secret", r"AKIA[A-Z0-9]{16}(?![A-Za-z0-9])|(?:[0-9a-f]{64}|[0-9a-f]{40}|[0-9a-f]{32}|[0-9A-F]{64}|[0-9A-F]{40}|[0-9A-F]{32})(?![A-Za-z0-9])|(?<=password=)[0-9a-f]{8,64}(?![A-Za-z0-9])", _secret),
    ("ip", r"\d{1,3}(?:\.\d{1,3}){3}(?![\d]|\.\d)", _ip),
    ("date", r"(?:\d{4}[-/.]\d{1,2}[-/.]\d{1,2}|\d{1,2}[-/.]\d{1,2}[-/.]\d{4})(?!\d|[-/]\d)", _date),
    ("ssn", r"\d{3}-\d{2}-\d{4}(?!\d|-\d)", _ssn),
    ("card", r"\d(?:[ -]?\d){12,18}(?![\d])", _card),
    ("phone", r"\+\d{1,3}[ .-]?\(?\d{1,4}\)?(?:[ .-]?\d{2,4}){2,4}(?!\d)|\(\d{3}\) ?\d{3}[ .-]\d{4}(?!\d)|\d{3}[.-]\d{3}[.-]\d{4}(?!\d)", _phone),
)
_ANY = re.compile("|".join(f"(?P<{n}>{p})" for n, p, _ in KINDS))
_EACH = [(n, re.compile(p), f) for n, p, f in KINDS]
_NEAR = re.compile(r"[@\d]|AKIA")
_GAP = re.compile(r"[\x00-\x20\u0085 ]")
_INSIDE = re.compile(r"[A-Za-z0-9]")


def found(text: str, key: bytes, back: bool = False) -> list[tuple[int, int, str, str]]:
    """(start, end, kind, pseudonym) of every valid value, in the text's order."""
    out, done, tried = [], 0, 0
    for near in _NEAR.finditer(text):
        at = near.start()
        if at < done:
            continue
        start = at
        while start > tried and start > done and at - start < 128 and not _GAP.match(text, start - 1):
            start -= 1
        while start <= at:
            tried = start + 1
            if start and _INSIDE.match(text, start - 1) and _INSIDE.match(text, start):
                start += 1
                continue
            hit = None
            for name, pattern, permute in _EACH if _ANY.match(text, start) else ():
                m = pattern.match(text, start)
                new = permute(m[0], key, back) if m else None
                if new is not None:
                    hit = (start, m.end(), name, new)
                    break
            if hit:
                out.append(hit)
                done = tried = hit[1]
                break
            start += 1
    return out


def veil(text: str | None, key: bytes, back: bool = False) -> tuple[str | None, list[tuple[int, int, str, str]]]:
    if not text:
        return text, []
    spans = found(text, key, back)
    parts, last = [], 0
    for a, b, _, new in spans:
        parts += [text[last:a], new]
        last = b
    return "".join([*parts, text[last:]]) if spans else text, spans


def unveil(text: str | None, key: bytes) -> str | None:
    """The text before :func:`veil`, for those who hold the key; dates with one-digit parts come back with two."""
    return veil(text, key, True)[0]


def pseudonymise(docs: DataFrame, key: bytes) -> DataFrame:
    """One row per row of docs: doc_id, text with pseudonyms, n_found, and found: kind, start and length in the text as it was, and pseudonym."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int32()), ("length", pa.int32()), ("pseudonym", pa.string())]))
        again = lru_cache(1024)(lambda text: veil(text, key))
        for batch in batches:
            done = [again(x) for x in batch.column(1).to_pylist()]
            spans = [[{"kind": n, "start": a, "length": b - a, "pseudonym": new} for a, b, n, new in s] for _, s in done]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([t for t, _ in done], pa.string()), pa.array([len(s) for s in spans], pa.int64()), pa.array(spans, kind)], names=["doc_id", "text", "n_found", "found"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", F.col("text")).mapInArrow(run, f"doc_id {kind}, text string, n_found long, found array<struct<kind:string,start:int,length:int,pseudonym:string>>")
