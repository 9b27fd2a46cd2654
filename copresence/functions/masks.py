"""Class sets as 63-bit masks: columns and plain-number helpers."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

MAX_BITS = 63


def bit_mask(bit: str) -> Column:
    """The mask with the one bit that column `bit` names."""
    return F.expr(f"shiftleft(1L, CAST({bit} AS INT))")


def fold(mask: str | Column) -> Column:
    """Union of sets; partial on the map side, order and repeats don't matter."""
    return F.bit_or(mask)


def size(mask: str | Column) -> Column:
    return F.bit_count(mask).cast("int")


def contains(mask: str, items: str) -> Column:
    return F.expr(f"({mask} & {items}) = {items}")


def bits(mask: str | Column) -> Column:
    """Ascending bit numbers of a mask."""
    m = F.col(mask) if isinstance(mask, str) else mask
    return F.filter(F.sequence(F.lit(0), F.lit(MAX_BITS - 1)), lambda b: F.bit_get(m, b) == 1)


def codes(mask: str | Column, code_of_bit: list[int]) -> Column:
    """Ascending class codes of a mask (code_of_bit is ascending)."""
    table = F.array(*[F.lit(c) for c in code_of_bit])
    return F.transform(bits(mask), lambda b: F.get(table, b))


def itemset_key(mask: str | Column, code_of_bit: list[int]) -> Column:
    return F.array_join(F.transform(codes(mask, code_of_bit), lambda c: c.cast("string")), "|")


def mask_of(numbers: list[int]) -> int:
    return sum(1 << b for b in set(numbers))
