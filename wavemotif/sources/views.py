"""Series views: the given tables as rows (sensor, series_id, t, v); v is the value in integer hundredths.

Integers make moments exact and independent of the order of summation, so results do not depend on partitioning.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

WEEKS = 357
HOURS = 720
EPOCH = "1995-01-02"
BLOCK = 60
JITTER = 11
# fixed values: the planted pair of shapes over 20 steps, in hundredths
HELD_STEP = [0] * 10 + [3000] * 8 + [0] * 2
TWO_PULSES = [3000 if i in (2, 3, 14, 15) else 0 for i in range(20)]


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def run_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    """events: a run a user, steps by (ts, event_id)."""
    order = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return load(spark, sf_dir, "events").select(F.lit("value").alias("sensor"), F.col("user_id").alias("series_id"), (F.row_number().over(order) - 1).cast("long").alias("t"), F.round(F.col("value") * 100).cast("long").alias("v"))


def clock_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    """events: a sensor an event type, hourly sums of hundredths over 30 days; hours without events repeat the last value."""
    hours = F.timestamp_diff("HOUR", F.lit("2024-01-01").cast("timestamp_ntz"), F.col("ts"))
    known = load(spark, sf_dir, "events").select(F.col("event_type").alias("sensor"), on_grid(hours.cast("long"), HOURS).alias("t"), F.round(F.col("value") * 100).cast("long").alias("v")).groupBy("sensor", "t").agg(F.sum("v").alias("v"))
    return fill_previous(known, HOURS).select("sensor", F.lit(0).cast("long").alias("series_id"), "t", "v")


def on_grid(t: Column, steps: int) -> Column:
    """t, or an error where it lies outside of the grid 0 .. steps - 1: no row is left out without a word."""
    return F.when(t.between(0, steps - 1), t).otherwise(F.raise_error(F.lit(f"a row lies outside of the grid of {steps} steps")).cast("long"))


def fill_previous(known: DataFrame, steps: int) -> DataFrame:
    """(sensor, t, v) on the grid 0 .. steps - 1; steps before the first value are left out."""
    grid = known.select("sensor").distinct().select("sensor", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(steps - 1).cast("long"))).alias("t"))
    w = Window.partitionBy("sensor").orderBy("t").rowsBetween(Window.unboundedPreceding, 0)
    return grid.join(known, ["sensor", "t"], "left").withColumn("v", F.last("v", ignorenulls=True).over(w)).where("v is not null")


def flag_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lineitem: six long runs by return flag and line status, daily quantity."""
    rows = load(spark, sf_dir, "lineitem").select(F.concat("l_returnflag", "l_linestatus").alias("flag"), F.to_date("l_shipdate").alias("day"), F.round(F.col("l_quantity") * 100).cast("long").alias("v"))
    daily = rows.groupBy("flag", "day").agg(F.sum("v").alias("v"))
    ids = rows.select("flag").distinct().withColumn("series_id", (F.row_number().over(Window.orderBy("flag")) - 1).cast("long"))  # six rows
    return daily.join(F.broadcast(ids), "flag").select(F.lit("quantity").alias("sensor"), "series_id", (F.row_number().over(Window.partitionBy("series_id").orderBy("day")) - 1).cast("long").alias("t"), "v")


def region_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    """orders by customer, nation and region: a sensor an order priority, a run a region, daily totals in cents."""
    o, c, n = (load(spark, sf_dir, x) for x in ("orders", "customer", "nation"))
    rows = o.join(c, o.o_custkey == c.c_custkey).join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey"))
    daily = rows.groupBy(F.col("o_orderpriority").alias("sensor"), F.col("n_regionkey").cast("long").alias("series_id"), F.to_date("o_orderdate").alias("day")).agg(F.sum(F.round(F.col("o_totalprice") * 100).cast("long")).alias("v"))
    return daily.select("sensor", "series_id", (F.row_number().over(Window.partitionBy("sensor", "series_id").orderBy("day")) - 1).cast("long").alias("t"), "v")


def fleet_view(spark: SparkSession, sf_dir: str, sensors: tuple[str, ...] | None = None) -> DataFrame:
    """lineitem: a run a supplier, weekly sums on a dense grid with zeros, six sensors."""
    week = F.floor(F.datediff(F.to_date("l_shipdate"), F.lit(EPOCH).cast("date")) / 7).cast("long")
    hundred = lambda c: F.sum(F.round(F.col(c) * 100).cast("long"))
    weekly = load(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("series_id"), on_grid(week, WEEKS).alias("t"), "l_orderkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax")
    weekly = weekly.groupBy("series_id", "t").agg(hundred("l_quantity").alias("quantity"), hundred("l_extendedprice").alias("price"), hundred("l_discount").alias("discount"), hundred("l_tax").alias("tax"), (F.count("*") * 100).alias("lines"), (F.count_distinct("l_orderkey") * 100).alias("orders"))
    names = ["quantity", "price", "discount", "tax", "lines", "orders"]
    grid = weekly.select("series_id").distinct().select("series_id", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(WEEKS - 1).cast("long"))).alias("t"))
    dense = grid.join(weekly, ["series_id", "t"], "left").fillna(0, names)
    return dense.unpivot(["series_id", "t"], [n for n in names if not sensors or n in sensors], "sensor", "v").select("sensor", "series_id", "t", "v")


def planted_view(spark: SparkSession, sf_dir: str, level_step: int = 0) -> DataFrame:
    """A tenth of the fleet's quantity with both shapes in every full block of 60 weeks, at jittered places."""
    b, k, u = F.floor(F.col("t") / BLOCK).cast("long"), F.col("series_id"), F.col("t") % BLOCK
    a_pos = u - 2 - (7 * k + 13 * b) % 11
    b_pos = u - 29 - (5 * k + 17 * b) % 11
    at = lambda shape, pos: F.coalesce(F.when(pos.between(0, 19), F.element_at(F.array(*map(F.lit, shape)), (pos + 1).cast("int"))), F.lit(0))
    planted = F.when(b < WEEKS // BLOCK, at(HELD_STEP, a_pos) + at(TWO_PULSES, b_pos) + level_step * 100 * (b % 2)).otherwise(0)
    return fleet_view(spark, sf_dir, ("quantity",)).withColumn("v", (F.round(F.col("v") / 10).cast("long") + planted).cast("long"))


def planted_truth(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(series_id, t, shape): where the planted shapes start."""
    runs = load(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("series_id")).distinct().withColumn("b", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(WEEKS // BLOCK - 1).cast("long"))))
    a = runs.select("series_id", (F.col("b") * BLOCK + 2 + (7 * F.col("series_id") + 13 * F.col("b")) % 11).alias("t"), F.lit("held_step").alias("shape"))
    return a.unionByName(runs.select("series_id", (F.col("b") * BLOCK + 29 + (5 * F.col("series_id") + 17 * F.col("b")) % 11).alias("t"), F.lit("two_pulses").alias("shape")))


def text_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    """documents: a run a document, the lengths of its words up to 15."""
    words = F.regexp_extract_all(F.coalesce("text", F.lit("")), F.lit(r"[^\x20\x09-\x0D]+"), F.lit(0))
    return load(spark, sf_dir, "documents").select(F.col("doc_id").alias("series_id"), F.posexplode(words).alias("t", "word")).select(F.lit("word_length").alias("sensor"), "series_id", F.col("t").cast("long").alias("t"), (F.least(F.length("word"), F.lit(15)) * 100).cast("long").alias("v"))


def cumulative(series: DataFrame) -> DataFrame:
    """Running sums of n * v - sum(v): the deviations from the mean of the run, times its length."""
    key = Window.partitionBy("sensor", "series_id")
    up = key.orderBy("t").rowsBetween(Window.unboundedPreceding, 0)
    return series.withColumn("dev", F.count("*").over(key) * F.col("v") - F.sum("v").over(key)).select("sensor", "series_id", "t", F.sum("dev").over(up).alias("v"))


def smoothed(series: DataFrame, width: int = 7) -> DataFrame:
    """Sums over the last width steps; steps without that many are left out."""
    w = Window.partitionBy("sensor", "series_id").orderBy("t").rowsBetween(1 - width, 0)
    return series.select("sensor", "series_id", "t", F.sum("v").over(w).alias("v"), F.count("*").over(w).alias("c")).where(F.col("c") == width).drop("c")


VIEWS = {"run": run_view, "clock": clock_view, "flag": flag_view, "region": region_view, "fleet": fleet_view, "text": text_view, "planted": planted_view}
