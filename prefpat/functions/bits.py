"""Item sets as 64-bit mask words ``m0 .. m{W-1}``.

Words are plain long columns, so containment and parities stay inside generated
code. Bit 63 makes a word negative: only bitwise tests are used, never order.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

WORD = 64


def words_for(n_items: int) -> int:
    return max(1, -(-n_items // WORD))


def mask_names(words: int, prefix: str = "m") -> list[str]:
    return [f"{prefix}{w}" for w in range(words)]


def signed(word: int) -> int:
    """An unsigned 64-bit word as the signed value that a long column holds."""
    return word - (1 << 64) if word >> 63 else word


def pack_item(item_id: Column, words: int) -> list[Column]:
    """Mask words of a group's items: one bitwise-or aggregate for each word."""
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), (item_id % WORD).cast("int"))
    word = F.floor(item_id / WORD)
    return [F.coalesce(F.bit_or(F.when(word == w, bit)), F.lit(0).cast("long")).alias(f"m{w}") for w in range(words)]


def pack_array(items: Column, words: int) -> list[Column]:
    """Mask words of an array of item ids."""
    out = []
    for w in range(words):
        own = F.filter(items, lambda i: F.floor(i / WORD) == w)  # noqa: B023
        out.append(F.aggregate(own, F.lit(0).cast("long"), lambda a, i: a.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("long"), (i % WORD).cast("int")))).alias(f"m{w}"))
    return out


def ids(masks: list[str]) -> Column:
    """Sorted item ids of mask words."""
    own = lambda w, m: F.filter(F.sequence(F.lit(w * WORD), F.lit(w * WORD + WORD - 1)), lambda i: F.call_function("shiftrightunsigned", F.col(m), i % WORD).bitwiseAND(F.lit(1).cast("long")) == 1)
    return F.concat(*[own(w, m) for w, m in enumerate(masks)])


def contains(outer: list[Column], inner: list[Column]) -> Column:
    """Is the inner set a subset of the outer one?"""
    return reduce(lambda a, b: a & b, (o.bitwiseAND(i) == i for o, i in zip(outer, inner)))


def overlap(a: list[Column], b: list[Column]) -> Column:
    """Number of items in both."""
    return reduce(lambda x, y: x + y, (F.bit_count(x.bitwiseAND(y)) for x, y in zip(a, b)))


def size(a: list[Column]) -> Column:
    return reduce(lambda x, y: x + y, (F.bit_count(x) for x in a))


def parity(masks: list[Column], coefficients: list[Column]) -> Column:
    """Parity of the items that a constraint involves: fold the words, count once."""
    folded = reduce(lambda x, y: x.bitwiseXOR(y), (m.bitwiseAND(c) for m, c in zip(masks, coefficients)))
    return F.bit_count(folded) % 2


def jaccard(a: list[Column], b: list[Column]) -> Column:
    both = overlap(a, b)
    return both / (size(a) + size(b) - both)
