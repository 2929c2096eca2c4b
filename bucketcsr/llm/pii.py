"""Format-preserving pseudonyms by Feistel networks.

Patterns find candidates in whole texts; card, account and identity numbers, phones, addresses and dates are validated,
and only valid ones are replaced. A replacement is a keyed permutation inside the value's own format: a card maps to
a card with a right check digit, a date to a date in the same notation, a mail address to one of equal shape. The
permutation is a balanced Feistel network over the format's own number range, with cycle walking where the range is no
square; it depends on key and format alone, so equal values stay equal across documents and the holder of the key can
invert it. One Arrow pass, no shuffle, no state.

Work is bounded by the text: every pattern has a longest match, ranges are whole numbers of any size (the longest mail address
has some 500 letters to permute), and a candidate is tested for overlap by bisection among the values already found.

Null text stays null. Repeated rows give equal rows. Extra columns go along untouched. The key has no default: who knows
it can invert all pseudonyms.
"""

from __future__ import annotations

import datetime
import hashlib
import math
import re
from bisect import bisect_left
from collections.abc import Callable
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame, functions as F, types as T

from .shared import map_text

ROUNDS = 8
KINDS = ("email", "iban", "card", "ssn", "phone", "ipv4", "date")


class Feistel:
    """A keyed permutation of 0 .. size - 1 for each format name."""

    def __init__(self, key: bytes) -> None:
        self.key = key

    def _round(self, name: bytes, i: int, half: int, side: int) -> int:
        """A keyed number below side, made of 16 bytes more than side has, so that it is close to uniform."""
        need = (side.bit_length() + 7) // 8 + 16
        seed = hashlib.blake2b(b"%s/%d/%x" % (name, i, half), key=self.key[:64]).digest()
        if need > len(seed):
            seed = hashlib.shake_256(seed).digest(need)
        return int.from_bytes(seed[:need], "big") % side

    def _pass(self, x: int, name: bytes, side: int, back: bool) -> int:
        left, right = divmod(x, side)
        if back:
            for i in range(ROUNDS - 1, -1, -1):
                left, right = (right - self._round(name, i, left, side)) % side, left
        else:
            for i in range(ROUNDS):
                left, right = right, (left + self._round(name, i, right, side)) % side
        return left * side + right

    def permute(self, x: int, size: int, name: str, back: bool = False) -> int:
        """Walks the cycle until the value is in range again; at most a few steps, as side squared hardly exceeds size."""
        if size < 2:
            return x
        side = math.isqrt(size - 1) + 1
        label = b"%s/%x" % (name.encode(), size)
        x = self._pass(x, label, side, back)
        while x >= size:
            x = self._pass(x, label, side, back)
        return x


def luhn(digits: str) -> int:
    """Check digit that completes the digits."""
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = int(c) * (2 if i % 2 == 0 else 1)
        total += d - 9 if d > 9 else d
    return -total % 10


def mod97(text: str) -> int:
    return int("".join(str(int(c, 36)) for c in text)) % 97


def _refill(shape: str, digits: str) -> str:
    """Digits put back into the places of the shape's digits."""
    left = iter(digits)
    return "".join(next(left) if c.isdigit() else c for c in shape)


def _number(f: Feistel, digits: str, name: str, back: bool) -> str:
    return str(f.permute(int(digits), 10 ** len(digits), f"{name}{len(digits)}", back)).zfill(len(digits)) if digits else ""


def _card(value: str, f: Feistel, back: bool) -> str | None:
    digits = re.sub(r"\D", "", value)
    if not 13 <= len(digits) <= 19 or luhn(digits[:-1]) != int(digits[-1]) or len(set(digits)) == 1:
        return None
    # the first digit names the network and stays
    body = digits[0] + _number(f, digits[1:-1], "card", back)
    return _refill(value, body + str(luhn(body)))


def _ssn(value: str, f: Feistel, back: bool) -> str | None:
    a, b, c = (int(x) for x in re.split(r"[- ]", value))
    if not 0 < a < 900 or a == 666 or not b or not c:
        return None
    areas = 898  # 001 to 899 without 666
    x = ((a - 1 - (a > 666)) * 99 + b - 1) * 9999 + c - 1
    x, c = divmod(f.permute(x, areas * 99 * 9999, "ssn", back), 9999)
    a, b = divmod(x, 99)
    return _refill(value, f"{a + 1 + (a >= 665):03d}{b + 1:02d}{c + 1:04d}")


def _iban(value: str, f: Feistel, back: bool) -> str | None:
    flat = re.sub(r"\s", "", value)
    if not 15 <= len(flat) <= 34 or mod97(flat[4:] + flat[:4]) != 1:
        return None
    digits = "".join(c for c in flat[4:] if c.isdigit())
    body = _refill(flat[4:], _number(f, digits, "iban" + flat[:2], back))
    check = 98 - mod97(body + flat[:2] + "00")
    new = iter(f"{flat[:2]}{check:02d}{body}")
    return "".join(c if c.isspace() else next(new) for c in value)


def _phone(value: str, f: Feistel, back: bool) -> str | None:
    digits = re.sub(r"\D", "", value)
    if not 9 <= len(digits) <= 15:
        return None
    # the country code stays
    head = re.match(r"\+(1|\d{2})", value)
    fixed = len(head.group(1)) if head else 0
    return _refill(value, digits[:fixed] + _number(f, digits[fixed:], f"phone{digits[:fixed]}", back))


def _ipv4(value: str, f: Feistel, back: bool) -> str | None:
    parts = [int(p) for p in value.split(".")]
    if max(parts) > 255 or any(len(p) > 1 and p[0] == "0" for p in value.split(".")):
        return None
    # octets keep their numbers of digits, so the address keeps its length
    first, sizes = zip(*[((0, 10), (10, 90), (100, 156))[len(p) - 1] for p in value.split(".")], strict=True)
    x, size = 0, 1
    for octet, lo, n in zip(parts, first, sizes, strict=True):
        x, size = x * n + octet - lo, size * n
    x = f.permute(x, size, "ipv4" + "".join(str(len(p)) for p in value.split(".")), back)
    new = []
    for lo, n in zip(reversed(first), reversed(sizes), strict=True):
        x, d = divmod(x, n)
        new.append(str(lo + d))
    return ".".join(reversed(new))


FIRST_DAY, DAYS = datetime.date(1900, 1, 1).toordinal(), datetime.date(2100, 1, 1).toordinal() - datetime.date(1900, 1, 1).toordinal()


def _date(value: str, f: Feistel, back: bool) -> str | None:
    a, mark, b, c = re.match(r"(\d+)([-/.])(\d+)\2(\d+)", value).groups()
    try:
        if len(a) == 4:
            day, order = datetime.date(int(a), int(b), int(c)), "ymd"
        elif int(a) > 12 or mark == ".":
            day, order = datetime.date(int(c), int(b), int(a)), "dmy"
        else:
            day, order = datetime.date(int(c), int(a), int(b)), "mdy"
    except ValueError:
        return None
    x = day.toordinal() - FIRST_DAY
    if not 0 <= x < DAYS:
        return None
    if order == "ymd":
        new = datetime.date.fromordinal(FIRST_DAY + f.permute(x, DAYS, "date", back))
        return f"{new.year:04d}{mark}{new.month:02d}{mark}{new.day:02d}"
    # day-first and month-first notations tell themselves apart by a day over 12: each class is permuted in itself
    own = _class_days(order == "dmy" and mark != ".", mark == ".")
    new = datetime.date.fromordinal(FIRST_DAY + own[0][f.permute(own[1][x], len(own[0]), f"date-{order}-{mark}", back)])
    one, two = (new.day, new.month) if order == "dmy" else (new.month, new.day)
    return f"{one:02d}{mark}{two:02d}{mark}{new.year:04d}"


@lru_cache(maxsize=4)
def _class_days(late: bool, every: bool) -> tuple[list[int], dict[int, int]]:
    days = [x for x in range(DAYS) if every or not late or datetime.date.fromordinal(FIRST_DAY + x).day > 12]
    return days, {x: i for i, x in enumerate(days)}


def _email(value: str, f: Feistel, back: bool) -> str | None:
    """Letters and digits of the local part and of the domain but its last two labels are permuted; marks keep their places."""
    local, domain = value.rsplit("@", 1)
    labels = domain.split(".")
    own = [local, *labels[: max(0, len(labels) - 2)]]
    flat = "\0".join(own)
    low = [c for c in flat if c.islower() and c.isascii()]
    up = [c for c in flat if c.isupper() and c.isascii()]
    num = [c for c in flat if c.isdigit() and c.isascii()]
    shape = re.sub(r"[0-9]", "0", re.sub(r"[A-Z]", "A", re.sub(r"[a-z]", "a", flat)))
    # one number for all places together, so that equal shapes form one range
    x = 0
    for c in low:
        x = x * 26 + ord(c) - 97
    for c in up:
        x = x * 26 + ord(c) - 65
    for c in num:
        x = x * 10 + int(c)
    x = f.permute(x, 26 ** (len(low) + len(up)) * 10 ** len(num), f"email{shape}", back)
    made: list[str] = []
    for count, base, first in ((len(num), 10, 48), (len(up), 26, 65), (len(low), 26, 97)):
        part = []
        for _ in range(count):
            x, d = divmod(x, base)
            part.append(chr(first + d))
        made.append("".join(reversed(part)))
    nums, ups, lows = (iter(m) for m in made)
    new = "".join(next(lows) if c == "a" else next(ups) if c == "A" else next(nums) if c == "0" else o for c, o in zip(shape, flat, strict=True)).split("\0")
    return f"{new[0]}@{'.'.join([*new[1:], *labels[max(0, len(labels) - 2) :]])}"


#: kind, pattern, rule; tried in this order at each place.
RULES: list[tuple[str, str, Callable[[str, Feistel, bool], str | None]]] = [
    ("email", r"[A-Za-z0-9](?:[A-Za-z0-9._%+-]{0,62}[A-Za-z0-9_%+-])?@(?:[A-Za-z0-9](?:[A-Za-z0-9-]{0,61}[A-Za-z0-9])?\.){1,8}[A-Za-z]{2,24}", _email),
    ("iban", r"(?<![A-Za-z0-9])[A-Z]{2}\d{2}(?: ?[A-Z0-9]){11,30}(?![A-Za-z0-9])", _iban),
    ("ipv4", r"(?<![\d.])\d{1,3}\.\d{1,3}\.\d{1,3}\.\d{1,3}(?!\.?\d)", _ipv4),
    ("date", r"(?<![\d./-])(?:\d{4}([-/.])\d{2}\1\d{2}|\d{2}([-/.])\d{2}\2\d{4})(?![\d/-])", _date),
    ("ssn", r"(?<![\d-])\d{3}([- ])\d{2}\1\d{4}(?![\d-])", _ssn),
    ("phone", r"\+\d{1,3}[ .-]?(?:\(\d{1,4}\)[ .-]?)?\d{2,4}(?:[ .-]?\d{2,4}){1,4}(?!\d)|(?<![\d(])\(\d{3}\) ?\d{3}[ .-]\d{4}(?!\d)|(?<![\d.-])\d{3}[.-]\d{3}[.-]\d{4}(?![\d.-]?\d)", _phone),
    ("card", r"(?<![\dA-Za-z])\d(?:[ -]?\d){12,18}(?![\dA-Za-z])", _card),
]
_FINDERS = [(kind, re.compile(pattern), rule) for kind, pattern, rule in RULES]
_MAYBE = re.compile(r"[@\d]")


class Pseudonyms:
    """Replaces, or with back=True restores, the personal values of a text."""

    def __init__(self, key: bytes, kinds: frozenset[str] | None = None) -> None:
        self.feistel = Feistel(key)
        self.kinds = kinds

    def __call__(self, text: str, back: bool = False) -> tuple[str, list[tuple[str, int, int]]]:
        """New text and (kind, start, end) of what was replaced, in the new text; every replacement keeps its length."""
        if not _MAYBE.search(text):
            return text, []
        taken: list[tuple[int, int, str, str]] = []  # sorted and disjoint
        for kind, finder, rule in _FINDERS:
            if (self.kinds and kind not in self.kinds) or (kind == "email" and "@" not in text):
                continue
            for m in finder.finditer(text):
                a, b = m.span()
                k = bisect_left(taken, (a,))
                if (k and taken[k - 1][1] > a) or (k < len(taken) and taken[k][0] < b):
                    continue
                new = rule(m.group(), self.feistel, back)
                if new is not None:
                    taken.insert(k, (a, b, kind, new))
        if not taken:
            return text, []
        out, at = [], 0
        for a, b, _, new in taken:
            out += [text[at:a], new]
            at = b
        return "".join([*out, text[at:]]), [(kind, a, b) for a, b, kind, _ in taken]


def pseudonymise(docs: DataFrame, key: str, text: str = "text", keep: list[str] | None = None, back: bool = False) -> DataFrame:
    """keep columns (default: all but the text) + the text with pseudonyms, n_values (long), kinds (string, sorted).

    Columns of docs named n_values or kinds are replaced. back restores the texts that the same key made.
    """
    if not key:
        raise ValueError("pseudonyms need a secret key")
    keep = [c for c in (docs.columns if keep is None else keep) if c.lower() not in ("n_values", "kinds", text.lower())]
    replace = Pseudonyms(hashlib.blake2b(key.encode(), digest_size=32).digest())

    def make(texts: pa.Array) -> list[pa.Array]:
        made = [(None, []) if t is None else replace(t, back) for t in texts.to_pylist()]
        return [pa.array([m[0] for m in made], pa.string()), pa.array([len(m[1]) for m in made], pa.int64()), pa.array([",".join(sorted({k for k, _, _ in m[1]})) for m in made], pa.string())]

    fields = [T.StructField(text, T.StringType()), T.StructField("n_values", T.LongType()), T.StructField("kinds", T.StringType())]
    return map_text(docs, text, fields, make, keep)
