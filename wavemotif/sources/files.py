"""Series from files and generators, and what is written: stages, exports, models."""

from __future__ import annotations

import json
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from wavemotif.sources.views import BLOCK, HELD_STEP, JITTER, TWO_PULSES

SERIES = "sensor string, series_id long, t long, v long"


def read_series(spark: SparkSession, path: str, fmt: str = "csv", schema: str = SERIES) -> DataFrame:
    """SERIES from csv (with a header), json lines or parquet; a row without its key or step, or that cannot be parsed, stops the query."""
    reader = spark.read.schema(schema)
    rows = (reader.option("header", True) if fmt == "csv" else reader).option("mode", "FAILFAST").format(fmt).load(path)
    missing = F.col("sensor").isNull() | F.col("series_id").isNull() | F.col("t").isNull()
    return rows.where(F.when(missing, F.raise_error(F.lit("a row of a series lacks sensor, series_id or t")).cast("boolean")).otherwise(True))


def export(df: DataFrame, path: str, fmt: str = "csv") -> None:
    writer = df.write.mode("overwrite").format(fmt)
    (writer.option("header", True) if fmt == "csv" else writer).save(path)


def write_stage(df: DataFrame, path: str, buckets: int = 64) -> None:
    """A stage that many runs read: Parquet by sensor and bucket of runs, sorted by run and step, so both prune the scan."""
    keyed = df.withColumn("series_bucket", F.pmod(F.xxhash64("series_id"), F.lit(buckets)).cast("int"))
    keyed.repartition("sensor", "series_bucket").sortWithinPartitions("sensor", "series_bucket", "series_id", "t").write.mode("overwrite").partitionBy("sensor", "series_bucket").parquet(path)


def read_stage(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path).drop("series_bucket")


def save_model(motifs: DataFrame, path: str, **params) -> None:
    """Motifs (sensor, motif_id, centroid, ..) and the parameters that matching needs."""
    motifs.write.mode("overwrite").parquet(f"{path}/motifs")
    motifs.sparkSession.createDataFrame([(json.dumps(params, sort_keys=True),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/params")


def load_model(spark: SparkSession, path: str) -> tuple[DataFrame, dict]:
    return spark.read.parquet(f"{path}/motifs"), json.loads(spark.read.text(f"{path}/params").first().value)


class PlantedSource(DataSource):
    """format("planted"): runs of the two planted shapes without noise. Options: runs, blocks, partitions."""

    @classmethod
    def name(cls) -> str:
        return "planted"

    def schema(self) -> str:
        return SERIES

    def reader(self, schema) -> DataSourceReader:
        return PlantedReader({k: int(self.options.get(k, v)) for k, v in {"runs": 10, "blocks": 5, "partitions": 8}.items()})


class PlantedReader(DataSourceReader):
    def __init__(self, sizes: dict[str, int]):
        self.sizes = sizes

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(i) for i in range(self.sizes["partitions"])]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        for k in range(partition.value + 1, self.sizes["runs"] + 1, self.sizes["partitions"]):
            for t in range(self.sizes["blocks"] * BLOCK):
                b, u = divmod(t, BLOCK)
                a, p = u - 2 - (7 * k + 13 * b) % 11, u - 29 - (5 * k + 17 * b) % 11
                yield "planted", k, t, (HELD_STEP[a] if 0 <= a < 20 else 0) + (TWO_PULSES[p] if 0 <= p < 20 else 0)


def planted_runs(spark: SparkSession, runs: int = 10, blocks: int = 5, partitions: int = 8) -> DataFrame:
    spark.dataSource.register(PlantedSource)
    return spark.read.format("planted").options(runs=runs, blocks=blocks, partitions=partitions).load()


def planted_onto(series: DataFrame) -> DataFrame:
    """SERIES with the planted shapes added to each value, as sensor "planted". Places depend on the run and the block modulo JITTER only,
    so one period of the generated runs is broadcast (some 7,000 rows), whatever the number of runs and their length."""
    one = planted_runs(series.sparkSession, JITTER, JITTER).select((F.col("series_id") % JITTER).alias("_k"), F.col("t").alias("_u"), F.col("v").alias("_add"))
    rows = series.withColumn("_k", F.pmod("series_id", F.lit(JITTER))).withColumn("_u", F.col("t") % (JITTER * BLOCK))
    return rows.join(F.broadcast(one), ["_k", "_u"]).select(F.lit("planted").alias("sensor"), "series_id", "t", (F.col("v") + F.col("_add")).alias("v"))
