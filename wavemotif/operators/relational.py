"""Relational operators that the procedure and its users need beyond what Spark has by name."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, on: str, by: list[str], values: list[str], direction: str = "backward", tolerance: int | None = None) -> DataFrame:
    """left with the values of the row of right that is last at or before on (backward), first at or after it (forward), or nearest
    (ties to the earlier one). One union and one window: no pairs are made. left and right share on and by."""
    pack = F.struct(F.col(on).alias("at"), *[F.col(v) for v in values])
    names = left.columns
    both = left.withColumn("_side", F.lit(1)).withColumn("_row", F.lit(None).cast(right.select(pack.alias("p")).schema["p"].dataType))
    hits = right.select(*by, on, F.lit(0).alias("_side"), pack.alias("_row"))
    both = both.unionByName(hits, allowMissingColumns=True)
    back = Window.partitionBy(*by).orderBy(on, "_side").rowsBetween(Window.unboundedPreceding, 0)
    ahead = Window.partitionBy(*by).orderBy(on, F.desc("_side")).rowsBetween(0, Window.unboundedFollowing)
    both = both.withColumn("_b", F.last("_row", ignorenulls=True).over(back)).withColumn("_f", F.first("_row", ignorenulls=True).over(ahead)).where("_side = 1")
    before, after = F.col(on) - F.col("_b.at"), F.col("_f.at") - F.col(on)
    pick: Column = {"backward": F.col("_b"), "forward": F.col("_f")}.get(direction, F.when(F.col("_f").isNull() | (before <= after), F.col("_b")).otherwise(F.col("_f")))
    out = both.withColumn("_m", pick)
    if tolerance is not None:
        out = out.withColumn("_m", F.when(F.abs(F.col("_m.at") - F.col(on)) <= tolerance, F.col("_m")))
    return out.select(*names, F.col("_m.at").alias(f"{on}_matched"), *[F.col(f"_m.{v}").alias(v) for v in values])


def range_join(points: DataFrame, spans: DataFrame, at: str, lo: str, hi: str, by: list[str], width: int) -> DataFrame:
    """Rows of points and spans with lo <= at <= hi and equal by, through bins of a width: an equi-join and a residual test."""
    left = points.withColumn("_bin", F.floor(F.col(at) / width))
    right = spans.withColumn("_bin", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor(F.col(hi) / width))))
    return left.join(right, [*by, "_bin"]).where(F.col(at).between(F.col(lo), F.col(hi))).drop("_bin")


def interval_join(events: DataFrame, spans: DataFrame, at: str, lo: str, hi: str, by: list[str], seconds: int) -> DataFrame:
    """range_join over timestamps, to the microsecond, with bins of the given seconds."""
    micros = lambda c: F.unix_micros(F.col(c).cast("timestamp"))
    left = events.withColumn("_at", micros(at))
    right = spans.withColumn("_lo", micros(lo)).withColumn("_hi", micros(hi))
    return range_join(left, right, "_at", "_lo", "_hi", by, seconds * 1_000_000).drop("_at", "_lo", "_hi")


def islands(df: DataFrame, by: list[str], on: str, max_gap: int) -> DataFrame:
    """df with island: the number, from 0, of the stretch without a gap over max_gap."""
    order = Window.partitionBy(*by).orderBy(on)
    return df.withColumn("_new", F.when(F.col(on) - F.lag(on).over(order) > max_gap, 1).otherwise(0)).withColumn("island", F.sum("_new").over(order)).drop("_new")


def top_per_group(df: DataFrame, by: list[str], order: list[Column], k: int) -> DataFrame:
    return df.withColumn("rank", F.row_number().over(Window.partitionBy(*by).orderBy(*order))).where(F.col("rank") <= k)


def sample_rows(df: DataFrame, key: str, percent: int) -> DataFrame:
    """The same rows in every run and engine, by a multiplicative hash of an integer key."""
    return df.where((F.col(key) * 7919 + 13) % 104_729 % 100 < percent)
