"""Joins for keys that hold a large share of all rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def salted_join(big: DataFrame, small: DataFrame, key: str, spread: list[str], salts: int = 8, how: str = "inner") -> DataFrame:
    """Equi-join on ``key`` whose big side is dealt over ``salts`` tasks a key by a hash of ``spread``.

    The small side is repeated ``salts`` times, so the result is that of the plain join;
    a salt is a function of the row, so a task that runs again deals alike."""
    if how not in ("inner", "left"):
        raise ValueError("only the big side's rows may be kept unmatched")
    dealt = big.withColumn("_salt", F.pmod(F.xxhash64(*spread), F.lit(salts)).cast("int"))
    copies = small.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return dealt.join(copies, [key, "_salt"], how).drop("_salt")


def estimated_bytes(df: DataFrame) -> int:
    """The optimizer's estimate of a plan's size."""
    return int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))


def broadcast_under(df: DataFrame, max_bytes: int = 64 << 20) -> DataFrame:
    """``df`` marked for broadcast where its estimated size allows it, else as it is: the join then exchanges both sides."""
    return F.broadcast(df) if estimated_bytes(df) <= max_bytes else df


def guarded_cross(left: DataFrame, right: DataFrame, max_rows: int = 1_000_000) -> DataFrame:
    """All pairs of two small relations; refused where they would be more than ``max_rows``."""
    n, m = left.count(), right.count()
    if n * m > max_rows:
        raise ValueError(f"{n} x {m} pairs are more than {max_rows}")
    return left.crossJoin(F.broadcast(right) if m <= n else right)


def range_join(points: DataFrame, ranges: DataFrame, at: str, low: str, high: str, width: float, on: tuple[str, ...] = ()) -> DataFrame:
    """Pairs with low <= at <= high (and equal ``on`` columns): an equi-join on bins of ``width``, then the exact test.

    A range goes to every bin that it meets, a point to its own; rows with nulls in these columns meet nothing."""
    bin_of = lambda c: F.floor(F.col(c) / F.lit(width)).cast("bigint")
    whole = ranges.filter(F.col(low) <= F.col(high))
    dealt = whole.withColumn("_bin", F.explode(F.sequence(bin_of(low), bin_of(high))))
    placed = points.filter(F.col(at).isNotNull()).withColumn("_bin", bin_of(at))
    return placed.join(dealt, ["_bin", *on]).filter((F.col(at) >= F.col(low)) & (F.col(at) <= F.col(high))).drop("_bin")
