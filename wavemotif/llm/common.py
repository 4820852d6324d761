"""What the operators of this subpackage share: text batches, word hashes, shared tables, components.

Texts travel as Arrow batches and are worked on in small slices, so that a worker never holds more
than a few megabytes of Python objects. Tables that are read more than once are written as Parquet
under the folder that ``spark.checkpoint.dir`` names, which every executor sees; the lineage is cut
there, so a lost executor costs a re-read and not a recomputation.
"""

from __future__ import annotations

import atexit
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

SLICE_ROWS = 512
WORD_CACHE = 400_000
#: Largest number of 8-byte ids that is ever broadcast (32 MB); beyond it the same join is shuffled.
BROADCAST_IDS = 4_000_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


# ---------------------------------------------------------------- shared tables
class Workspace:
    """Parquet tables of one run, in a folder of its own under the shared checkpoint folder."""

    _own: str | None = None

    def __init__(self, spark: SparkSession):
        self.spark = spark
        base = spark.conf.get("spark.checkpoint.dir", None)
        if not base:
            if not spark.sparkContext.master.startswith("local["):
                raise ValueError("spark.checkpoint.dir must name a folder that all executors see")
            Workspace._own = Workspace._own or tempfile.mkdtemp(prefix="wavemotif-")  # one machine: tests
            base = f"file://{Workspace._own}"
        self.base = f"{base.rstrip('/')}/run-{uuid.uuid4().hex}"
        atexit.register(self._remove, self.base)

    def save(self, df: DataFrame, name: str, **measures: Column) -> DataFrame:
        """df as a table of its own. Its number of rows, and aggregates named in measures, are taken as it is written: see measured()."""
        path, seen = f"{self.base}/{name}-{uuid.uuid4().hex[:8]}", Observation()
        df.observe(seen, F.count(F.lit(1)).alias("rows"), *[c.alias(k) for k, c in measures.items()]).write.parquet(path)
        saved = self.spark.read.schema(df.schema).parquet(path)
        saved._kept_at, saved._measured = path, seen.get
        return saved

    def drop(self, *saved: DataFrame | None) -> None:
        """Frees tables that no later plan reads."""
        for df in saved:
            if df is not None and getattr(df, "_kept_at", None):
                self._remove(df._kept_at)

    def _remove(self, path: str) -> None:
        try:
            jvm = self.spark._jvm
            p = jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(p, True)
        except Exception:  # noqa: BLE001  the session may be gone at exit; nothing depends on it
            pass


def measured(saved: DataFrame, name: str = "rows"):
    """What was measured while a table was saved."""
    return saved._measured[name]


def semi_by_id(df: DataFrame, ids: DataFrame, n_ids: int, key: str = "doc_id") -> DataFrame:
    """Rows of df whose key is in ids: broadcast while the ids are few enough, else a shuffled semi join."""
    return df.join(F.broadcast(ids) if n_ids <= BROADCAST_IDS else ids, key, "left_semi")


def anti_by_id(df: DataFrame, ids: DataFrame, ws: Workspace) -> DataFrame:
    """df without the rows whose doc_id is in ids(doc_id); rows with a null doc_id stay. Texts are not shuffled while the ids are few enough."""
    gone = ws.save(ids.select(F.col("doc_id").alias("_gone")).distinct(), "gone")
    return df.join(F.broadcast(gone) if measured(gone) <= BROADCAST_IDS else gone, df["doc_id"] == gone["_gone"], "left_anti")


# ---------------------------------------------------------------- batches
def documents(df: DataFrame, *more: str) -> DataFrame:
    """doc_id, text and named columns with fixed types, whatever else the table holds."""
    return df.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), *[F.col(c) for c in more])


def map_batches(df: DataFrame, fn: Callable[[pa.RecordBatch], pa.RecordBatch], schema: T.StructType) -> DataFrame:
    """fn over slices of Arrow batches; fn returns a batch with the columns of schema."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, SLICE_ROWS):
                yield fn(batch.slice(at, SLICE_ROWS))

    return df.mapInArrow(run, schema)


def utf8(batch: pa.RecordBatch, name: str = "text") -> list[bytes]:
    """The column as UTF-8 bytes; null as empty."""
    return [x or b"" for x in batch.column(name).cast(pa.binary()).to_pylist()]


def strings(batch: pa.RecordBatch, name: str = "text") -> list[str]:
    return [x or "" for x in batch.column(name).to_pylist()]


# ---------------------------------------------------------------- hashes
class WordHashes(dict):
    """Word (bytes) to a 64-bit hash, remembered for the words seen last."""

    def __init__(self, of: Callable[[bytes], bytes] = lambda w: w):
        super().__init__()
        self.of = of

    def __missing__(self, word: bytes) -> int:
        if len(self) >= WORD_CACHE:
            self.clear()
        got = self[word] = xxhash.xxh3_64_intdigest(self.of(word))
        return got

    def array(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), np.uint64, len(words))


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser over 64 bits."""
    x = x ^ (x >> np.uint64(31))
    x = x * np.uint64(0x9E3779B97F4A7C15)
    x ^= x >> np.uint64(29)
    x *= np.uint64(0xD6E8FEB86659FD93)
    x ^= x >> np.uint64(32)
    return x


def shingle_hashes(words: np.ndarray, k: int) -> np.ndarray:
    """Hashes of all k-word shingles in order; of the whole sequence if it is shorter; none without words."""
    n = len(words)
    if not n:
        return words
    k = min(k, n)
    x = np.full(n - k + 1, 0x2545F4914F6CDD1D + k, np.uint64)
    for j in range(k):
        x = (x ^ words[j : n - k + 1 + j]) * np.uint64(0x5851F42D4C957F2D)
        x ^= x >> np.uint64(32)
    return mix64(x)


# ---------------------------------------------------------------- components
def connected_components(edges: DataFrame, ws: Workspace) -> DataFrame:
    """(id, component) for every id on an edge (a, b) of longs: component is the smallest id reachable.

    Alternates the large-star and small-star contractions; each is one aggregation and one join over the
    edges, which live in shared Parquet between rounds. Only a count and a checksum, taken as they are written, reach the driver.
    """
    check = {"sum": F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))}
    now, seen = ws.save(edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "edges", **check), None
    while measured(now) and (measured(now), measured(now, "sum")) != seen:
        seen = (measured(now), measured(now, "sum"))
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").select(F.explode(F.array(F.struct(F.greatest("v", "m").alias("u"), "m"), F.struct("u", "m"))).alias("e"))
        after = ws.save(small.select(F.col("e.u").alias("u"), F.col("e.m").alias("v")).where("u <> v").distinct(), "edges", **check)
        ws.drop(now)
        now = after
    return now.select(F.col("u").alias("id"), F.col("v").alias("component")).unionByName(now.select(F.col("v").alias("id"), F.col("v").alias("component")).distinct())
