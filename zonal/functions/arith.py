"""Exact integer arithmetic on columns."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def long(x: Column | int) -> Column:
    return F.lit(x).cast("long") if isinstance(x, int) else x


def floor_div(a: Column, b: Column | int) -> Column:
    """Floor of a / b for integers, b > 0; plain ``div`` would round towards zero."""
    b = long(b)
    return F.call_function("div", a - F.pmod(a, b), b)


def ceil_div(a: Column, b: Column | int) -> Column:
    return -floor_div(-a, b)


def spread_bits(v: Column) -> Column:
    """The low 24 bits of ``v`` moved to the even bit positions."""
    for shift, mask in ((16, 0x0000FFFF0000FFFF), (8, 0x00FF00FF00FF00FF), (4, 0x0F0F0F0F0F0F0F0F), (2, 0x3333333333333333), (1, 0x5555555555555555)):
        v = v.bitwiseOR(F.shiftleft(v, shift)).bitwiseAND(F.lit(mask).cast("long"))
    return v


def morton(x: Column, y: Column) -> Column:
    """Position on the Z-shaped space-filling curve."""
    return spread_bits(x.cast("long")).bitwiseOR(F.shiftleft(spread_bits(y.cast("long")), 1))


def hilbert(x: Column, y: Column, bits: int = 16) -> Column:
    """Position on the Hilbert curve over a square of 2^bits, by a fold over the bits."""
    start = F.struct(x.cast("long").alias("x"), y.cast("long").alias("y"), F.lit(0).cast("long").alias("d"))

    def step(acc: Column, k: Column) -> Column:
        s = F.call_function("shiftleft", F.lit(1).cast("long"), k)
        rx = F.when(acc["x"].bitwiseAND(s) > 0, 1).otherwise(0).cast("long")
        ry = F.when(acc["y"].bitwiseAND(s) > 0, 1).otherwise(0).cast("long")
        d = acc["d"] + s * s * (3 * rx).bitwiseXOR(ry)
        full = F.lit((1 << bits) - 1).cast("long")
        flip = (ry == 0) & (rx == 1)
        fx, fy = F.when(flip, full - acc["x"]).otherwise(acc["x"]), F.when(flip, full - acc["y"]).otherwise(acc["y"])
        return F.struct(F.when(ry == 0, fy).otherwise(fx).alias("x"), F.when(ry == 0, fx).otherwise(fy).alias("y"), d.alias("d"))

    return F.aggregate(F.array(*[F.lit(k) for k in range(bits - 1, -1, -1)]), start, step, lambda acc: acc["d"])
