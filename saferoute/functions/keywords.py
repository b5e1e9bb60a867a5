"""Keyword obstacles: exact test and bitmaps."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

BITS = 64


def keyword_blocked(kw: Column, s: Column) -> Column:
    """Whether an edge's keywords and the query's have one in common."""
    return F.coalesce(F.arrays_overlap(kw, s), F.lit(False))


def bitmap(kw: Column, words: int = 1, mode: str = "dict", bits: int = BITS) -> Column:
    """Words of 64 bits. 'dict': bit k for the keyword of code k (exact while codes are below 64 * words);
    'hashed': a bit of the first ``bits`` by hash, which can collide."""
    place = (lambda k: k.cast("int")) if mode == "dict" else (lambda k: F.pmod(F.xxhash64(k), F.lit(bits)).cast("int"))

    def word(i: int) -> Column:
        mine = F.filter(F.transform(kw, place), lambda p: F.floor(p / BITS) == i)
        return F.aggregate(mine, F.lit(0).cast("long"), lambda acc, p: acc.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("long"), p % BITS)))

    return F.array(*[word(i) for i in range(words)])


def bits_hit(a: Column, b: Column) -> Column:
    """Whether two bitmaps share a bit."""
    return F.exists(F.zip_with(a, b, lambda x, y: x.bitwiseAND(y)), lambda x: x != 0)


def blocked_by_bits(kw: Column, bits_: Column, s: Column, s_bits: Column, mode: str = "dict") -> Column:
    """Bitmap test; where bits may collide a hit is verified on the keywords."""
    hit = bits_hit(bits_, s_bits)
    return hit if mode == "dict" else hit & keyword_blocked(kw, s)
