"""Lexicographic pairs in one LONG, so that their least is a hash aggregate."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from walkfold.kernels.exprs import TOP

HALF = 2**31 - 1


def fits(first_most: int, second_most: int) -> bool:
    """Both sides must stay under 2^31."""
    return 0 <= first_most < HALF and 0 <= second_most < HALF


def pack(first: Column, second: Column, second_max: bool) -> Column:
    """Smaller is better; the second counts down if its greatest is wanted."""
    code = F.lit(HALF) - second if second_max else second
    return F.when(first.isNotNull() & second.isNotNull(), F.shiftleft(first.cast("long"), 32) + code.cast("long"))


def unpack(packed: Column, second_max: bool) -> tuple[Column, Column]:
    code = packed.bitwiseAND(F.lit(2**32 - 1))
    return F.shiftright(packed, 32), (F.lit(HALF).cast("long") - code if second_max else code)


def pack_sql(first: str, second: str, second_max: bool) -> str:
    code = f"{HALF}L - {second}" if second_max else second
    return f"CASE WHEN {first} IS NOT NULL AND {second} IS NOT NULL THEN shiftleft({first}, 32) + ({code}) END"


def unpack_sql(packed: str, second_max: bool) -> tuple[str, str]:
    code = f"({packed} & {2**32 - 1}L)"
    return f"shiftright({packed}, 32)", f"({HALF}L - {code})" if second_max else code


def shown(value: Column) -> Column:
    """The top capacity is shown as none."""
    return F.when(value != TOP, value)
