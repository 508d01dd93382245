"""Joins that Spark lacks: as-of, range and interval joins, and a salted join."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, *, on: str, by: list[str], values: list[str]) -> DataFrame:
    """``left`` with the ``values`` of the last row of ``right`` of the same ``by`` at or before ``on``.

    One union and one window, so work is a sort; never a join on an inequality. Ties at the same ``on``
    take the right row, and of several the greatest values.
    """
    pack = F.struct(*values)
    a = left.withColumn("_v", F.lit(None).cast(right.select(pack.alias("x")).schema["x"].dataType)).withColumn("_s", F.lit(1))
    b = right.select(*by, on, pack.alias("_v")).withColumn("_s", F.lit(0))
    w = Window.partitionBy(*by).orderBy(on, "_s", "_v").rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b, allowMissingColumns=True).withColumn("_l", F.last("_v", ignorenulls=True).over(w))
    return both.where("_s = 1").select(*left.columns, *[F.col(f"_l.{v}").alias(f"last_{v}") for v in values])


def range_join(points: DataFrame, ranges: DataFrame, *, point: str, low: str, high: str, width: float) -> DataFrame:
    """Points with the ranges [low, high) that hold them, meeting in bins of ``width``."""
    binned = lambda c: F.floor(c / F.lit(float(width)))
    a = points.withColumn("_bin", binned(F.col(point)))
    b = ranges.where(F.col(low) < F.col(high)).withColumn("_bin", F.explode(F.sequence(binned(F.col(low)), binned(F.col(high)))))
    return a.join(b, "_bin").where((F.col(point) >= F.col(low)) & (F.col(point) < F.col(high))).drop("_bin")


def interval_join(left: DataFrame, right: DataFrame, *, key: str, left_ts: str, right_ts: str, seconds: int) -> DataFrame:
    """Pairs of one key whose right time lies within ``seconds`` after the left one."""
    micros = lambda c: F.unix_micros(F.col(c).cast("timestamp"))
    bin_ = lambda c: F.floor(micros(c) / F.lit(seconds * 1_000_000))
    a = left.withColumn("_bin", bin_(left_ts))
    b = right.withColumn("_bin", F.explode(F.array(bin_(right_ts), bin_(right_ts) - 1)))
    gap: Column = micros(right_ts) - micros(left_ts)
    return a.join(b, [key, "_bin"]).where((gap >= 0) & (gap <= seconds * 1_000_000)).drop("_bin")


def salted_join(big: DataFrame, small: DataFrame, on: str, *, salts: int = 16) -> DataFrame:
    """An inner join whose hot keys of ``big`` are dealt over ``salts`` tasks; ``small`` is repeated as often."""
    a = big.withColumn("_salt", F.pmod(F.xxhash64(*big.columns), F.lit(salts)))
    b = small.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1)).cast("array<bigint>")))
    return a.join(b, [on, "_salt"]).drop("_salt")


#: Bytes of a side that is sent to all tasks.
BROADCAST_BYTES = 64 << 20


def row_bytes(df: DataFrame) -> Column:
    """Bytes of a row: UTF-8 of strings, bytes of binaries, 8 a number, elements of arrays at 8 and their strings."""
    size = {"string": F.octet_length, "binary": F.length, "array<string>": lambda c: F.octet_length(F.array_join(c, "")) + 8 * F.size(c), "array<int>": lambda c: 4 * F.size(c), "int": lambda c: F.lit(4), "boolean": lambda c: F.lit(1)}
    return sum((F.coalesce(size.get(kind, lambda c: F.lit(8))(F.col(c)), F.lit(0)) for c, kind in df.dtypes), F.lit(0))


def small_side(df: DataFrame, most: int = BROADCAST_BYTES) -> DataFrame:
    """``df``, sent to all tasks if its rows, summed, hold few bytes; left to be shuffled otherwise."""
    total = df.agg(F.sum(row_bytes(df) + 16).alias("b")).first()["b"] or 0
    return F.broadcast(df) if total <= most else df
