"""Attribute sets as BIGINT words: 63 bits a word, the lowest rank in the highest used bit.

With that packing, numeric order of the words is the lectic order of the sets, in Spark as in SQL.
"""

from __future__ import annotations

from collections.abc import Iterable, Sequence

from pyspark.sql import Column
from pyspark.sql import functions as F

WORD = 63
FULL = (1 << WORD) - 1


def width(m: int) -> int:
    """Words of a set over m attributes; at least one."""
    return max(1, -(-m // WORD))


def mask(rank: int) -> tuple[int, int]:
    """(word, bit mask) of an attribute rank."""
    return rank // WORD, 1 << (WORD - 1 - rank % WORD)


def pack(ranks: Iterable[int], words: int) -> tuple[int, ...]:
    out = [0] * words
    for r in ranks:
        w, b = mask(r)
        out[w] |= b
    return tuple(out)


def unpack(words: Sequence[int]) -> list[int]:
    return [w * WORD + k for w, x in enumerate(words) for k in range(WORD) if x >> (WORD - 1 - k) & 1]


def full_words(m: int) -> tuple[int, ...]:
    return pack(range(m), width(m))


def names_of(prefix: str, words: int) -> list[str]:
    return [f"{prefix}{i}" for i in range(words)]


def long(value: int) -> Column:
    return F.lit(value).cast("long")


def above_mask(rank: Column, word: int) -> Column:
    """Bits of one word that belong to ranks smaller than rank: the part of a set before p."""
    k = rank - word * WORD
    inside = long(FULL).bitwiseXOR(F.call_function("shiftleft", long(1), (WORD - k).cast("int")) - long(1))
    return F.when(k <= 0, long(0)).when(k >= WORD, long(FULL)).otherwise(inside)


def bit_mask(rank: Column, word: int) -> Column:
    """The bit of rank, if it lies in the word."""
    k = rank - word * WORD
    return F.when((k >= 0) & (k < WORD), F.call_function("shiftleft", long(1), (WORD - 1 - k).cast("int"))).otherwise(long(0))


def seed_words(d: Sequence[Column], rank: Column) -> list[Column]:
    """(d before p) with p: what the generating operation closes."""
    return [x.bitwiseAND(above_mask(rank, i)).bitwiseOR(bit_mask(rank, i)) for i, x in enumerate(d)]


def with_bit(d: Sequence[Column], rank: Column) -> list[Column]:
    return [x.bitwiseOR(bit_mask(rank, i)) for i, x in enumerate(d)]


def without_last(d: Sequence[Column]) -> list[Column]:
    """A set without its attribute of the largest rank."""
    later, out = F.lit(True), []
    for x in reversed(d):
        out.append(F.when(later & (x != 0), x.bitwiseAND(x - long(1))).otherwise(x))
        later = later & (x == 0)
    return out[::-1]


def has_rank(d: Sequence[Column], rank: Column) -> Column:
    return _any([x.bitwiseAND(bit_mask(rank, i)) != 0 for i, x in enumerate(d)])


def _any(tests: list[Column]) -> Column:
    out = tests[0]
    for t in tests[1:]:
        out = out | t
    return out


def _all(tests: list[Column]) -> Column:
    out = tests[0]
    for t in tests[1:]:
        out = out & t
    return out


def contains(big: Sequence[Column], small: Sequence[Column]) -> Column:
    return _all([b.bitwiseAND(s) == s for b, s in zip(big, small, strict=True)])


def disjoint(a: Sequence[Column], b: Sequence[Column]) -> Column:
    return _all([x.bitwiseAND(y) == 0 for x, y in zip(a, b, strict=True)])


def overlap(a: Sequence[Column], b: Sequence[Column]) -> Column:
    """How many attributes two sets share."""
    return sum((F.bit_count(x.bitwiseAND(y)) for x, y in zip(a, b, strict=True)), F.lit(0))


def equal(a: Sequence[Column], b: Sequence[Column]) -> Column:
    return _all([x == y for x, y in zip(a, b, strict=True)])


def lectic_less(a: Sequence[Column], b: Sequence[Column]) -> Column:
    """The smallest attribute in which the sets differ lies in b."""
    return F.struct(*[x.alias(f"x{i}") for i, x in enumerate(a)]) < F.struct(*[x.alias(f"x{i}") for i, x in enumerate(b)])


def lectic_less_at(a: Sequence[Column], b: Sequence[Column], rank: Column) -> Column:
    """The same, with that attribute being the one of the given rank."""
    same = _all([x.bitwiseAND(above_mask(rank, i)) == y.bitwiseAND(above_mask(rank, i)) for i, (x, y) in enumerate(zip(a, b, strict=True))])
    return same & has_rank(b, rank) & ~has_rank(a, rank)


def same_before(a: Sequence[Column], b: Sequence[Column], rank: Column) -> Column:
    return _all([x.bitwiseAND(above_mask(rank, i)) == y.bitwiseAND(above_mask(rank, i)) for i, (x, y) in enumerate(zip(a, b, strict=True))])


def size_of(d: Sequence[Column]) -> Column:
    return sum((F.bit_count(x) for x in d), F.lit(0))


def head_of(d: Sequence[Column], m: int) -> Column:
    """Rank of the leading attribute; m for the empty set."""
    leading = [F.when(x != 0, F.lit(i * WORD + WORD) - F.length(F.bin(x))) for i, x in enumerate(d)]
    return F.coalesce(*leading, F.lit(m)).cast("int")


def escape(name: str) -> str:
    """Names stand comma-joined in intents; commas and backslashes inside a name are escaped."""
    return name.replace("\\", "\\\\").replace(",", "\\,")


def intent_string(d: Sequence[Column], attributes: Sequence[str]) -> Column:
    """Names in rank order, comma-joined; the empty set is the empty string."""
    parts = []
    for rank, name in enumerate(attributes):
        w, b = mask(rank)
        parts.append(F.when(d[w].bitwiseAND(long(b)) != 0, F.lit(escape(name))))
    return F.concat_ws(",", *parts) if parts else F.lit("")


def intent_array(d: Sequence[Column], attributes: Sequence[str]) -> Column:
    parts = []
    for rank, name in enumerate(attributes):
        w, b = mask(rank)
        parts.append(F.when(d[w].bitwiseAND(long(b)) != 0, F.lit(name)))
    return F.array_compact(F.array(*parts)) if parts else F.array().cast("array<string>")


def packed_from_array(attrs: Column, attributes: Sequence[str]) -> list[Column]:
    """Words of an ARRAY<STRING>; names outside of the context are left out."""
    words = [long(0)] * width(len(attributes))
    for rank, name in enumerate(attributes):
        w, b = mask(rank)
        words[w] = words[w].bitwiseOR(F.when(F.array_contains(attrs, name), long(b)).otherwise(long(0)))
    return words
