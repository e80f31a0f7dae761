"""Mask arithmetic as expressions. Offset i of a node is bit b-1-i: first child, highest bit."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _name(c: Column | str) -> Column:
    return F.col(c) if isinstance(c, str) else c


def one_bit(offset: str, b: int) -> Column:
    """The mask with only ``offset`` (a SQL expression) set."""
    return F.expr(f"shiftleft(1L, cast({b - 1} - ({offset}) as int))")


def bits_on(mask: Column | str, b: int) -> Column:
    """Offsets of the set bits, ascending. Outside codegen (a lambda); for hot paths see ``explode_bits``."""
    m = _name(mask)
    return F.filter(F.sequence(F.lit(0), F.lit(b - 1)), lambda i: F.getbit(m, F.lit(b - 1) - i) == 1)


def explode_bits(df, mask: str, b: int, name: str = "bit"):
    """One row per set bit: a generator over b offsets and a bit filter, both within codegen."""
    return df.withColumn(name, F.explode(F.sequence(F.lit(0), F.lit(b - 1)))).where(F.getbit(F.col(mask), F.lit(b - 1) - F.col(name)) == 1)


def rank_before(mask: str, offset: str, b: int) -> Column:
    """Set bits of ``mask`` left of ``offset``: the rank of that child's mask among its siblings."""
    return F.expr(f"case when ({offset}) = 0 then 0 else bit_count(shiftrightunsigned({mask}, cast({b} - ({offset}) as int))) end")


def clip_from(mask: str, offset: str, b: int) -> Column:
    """Only the bits at ``offset`` and after it."""
    return F.expr(f"{mask} & shiftrightunsigned(-1L, cast({64 - b} + ({offset}) as int))")


def positions(df, mask: str, node: str, b: int):
    """``pos`` of every set bit of leaf masks."""
    return explode_bits(df, mask, b).withColumn("pos", F.col(node) * b + F.col("bit")).drop("bit")
