"""Mixing sources to target weights by capped water-filling.

A budget of words is shared over sources by weight. A source whose share would pass its cap (epochs
times its size) is clamped there and the excess is shared again by weight over the rest. The end of
that process has a closed form: with sources in order of cap / weight, the clamped ones are a prefix, so
one running sum over the table of sources (one row a source, never documents) gives every target.

A source is then repeated whole floor(target / size) times, and for the rest of its target documents are
taken in the order of a seeded hash until half of the next document would pass it. That order is cut by a
histogram: hash bins are summed before the shuffle, the bin in which the target falls is found from
sums, and only documents of that one bin are ordered. So a source with a third of all rows costs no more.

Defined cases: null text has size 0; a null source is a source of its own, last in order; a null doc_id takes
part with an empty key; repeated rows share a key and are taken together. Without words nothing is
taken. Further columns are not read, or kept as they are by materialise().
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from wavemotif.llm.common import Workspace, measured

WORD = r"[^\x20\x09-\x0D]+"
BIN_BITS = 10
#: Largest number of sources whose line of the plan is broadcast.
BROADCAST_SOURCES = 200_000


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def seeded_key(doc_id: Column, seed: int) -> Column:
    """32 bits of the MD5 of "seed:doc_id"."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(doc_id.cast("string"), F.lit(""))).cast("binary")), 1, 8), 16, 10).cast("long")


def water_fill(sources: DataFrame, weights: tuple[int, ...], share: float, epochs: float) -> DataFrame:
    """sources(source, source_size) with weight, target. Weights repeat over sources by code point, nulls last."""
    order = Window.orderBy(F.col("source").asc_nulls_last())
    nth = (F.row_number().over(order) - 1) % len(weights)
    w = sources.withColumn("weight", F.element_at(F.array(*[F.lit(x) for x in weights]), (nth + 1).cast("int")).cast("double"))
    w = w.withColumn("cap", epochs * F.col("source_size"))
    up = Window.orderBy(F.col("cap") / F.col("weight"), F.col("source").asc_nulls_last())
    before = up.rowsBetween(Window.unboundedPreceding, -1)
    everything = Window.partitionBy(F.lit(1))
    w = w.withColumn("budget", share * F.sum("source_size").over(everything))
    w = w.withColumn("level", (F.col("budget") - F.coalesce(F.sum("cap").over(before), F.lit(0.0))) / (F.sum("weight").over(everything) - F.coalesce(F.sum("weight").over(before), F.lit(0.0))))
    # level: what a unit of weight would get if exactly the sources before this one were clamped
    free = F.min(F.when(F.col("level") * F.col("weight") <= F.col("cap"), F.struct(F.col("cap") / F.col("weight"), "level"))).over(everything)
    w = w.withColumn("final", free["level"])
    return w.select("source", "source_size", "weight", F.when(F.col("final").isNull(), F.col("cap")).otherwise(F.least("cap", F.col("final") * F.col("weight"))).alias("target"))


def mix_plan(docs: DataFrame, weights: tuple[int, ...] = (5, 2, 1), share: float = 1.5, epochs: float = 2.0, seed: int = 7) -> tuple[DataFrame, DataFrame]:
    """(thin, plan): thin(doc_id, source, size, key) a row a document; plan(source, source_size, target, whole, last_key, last_id) a row a source.

    A document is taken whole times, and once more if (key, doc_id) <= (last_key, last_id).
    """
    ws = Workspace(docs.sparkSession)
    thin = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), word_count(F.col("text").cast("string")).alias("size"), seeded_key(F.col("doc_id"), seed).alias("key"))
    thin = ws.save(thin, "sizes")
    binned = thin.withColumn("bin", F.shiftright("key", 32 - BIN_BITS))
    bins = ws.save(binned.groupBy("source", "bin").agg(F.sum("size").alias("size")), "bins")
    filled = water_fill(bins.groupBy("source").agg(F.sum("size").alias("source_size")), weights, share, epochs)
    filled = filled.withColumn("whole", F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0)).cast("long"))
    filled = ws.save(filled.withColumn("rest", F.col("target") - F.col("whole") * F.col("source_size")), "targets")
    up = Window.partitionBy("source").orderBy("bin").rowsBetween(Window.unboundedPreceding, 0)
    sums = bins.withColumn("upto", F.sum("size").over(up)).join(filled.select(F.col("source").alias("s"), "rest"), F.col("source").eqNullSafe(F.col("s")))
    # the bin whose sum passes the rest; every bin before it is taken whole, but for its last document perhaps
    cut = sums.where("upto >= rest").groupBy("s", "rest").agg(F.min(F.struct("bin", (F.col("upto") - F.col("size")).alias("base"))).alias("m")).select("s", "rest", "m.bin", "m.base")
    near = binned.select("source", "doc_id", "size", "key", F.col("bin").alias("b")).join(cut, F.col("source").eqNullSafe(F.col("s")) & (F.col("b") == F.col("bin")))
    # repeated rows count as one step
    steps = near.groupBy("s", "rest", "base", "key", "doc_id").agg(F.sum("size").alias("size"))
    ordered = Window.partitionBy("s").orderBy("key", F.col("doc_id").asc_nulls_first()).rowsBetween(Window.unboundedPreceding, 0)
    steps = steps.withColumn("upto", F.col("base") + F.sum("size").over(ordered)).where("2 * upto - size <= 2 * rest")
    last = steps.groupBy(F.col("s").alias("of")).agg(F.max(F.struct("key", F.coalesce("doc_id", F.lit(-(2**63))).alias("doc_id"))).alias("m"))
    cut = cut.join(last, F.col("s").eqNullSafe(F.col("of")), "left").select("s", "bin", F.col("m.key").alias("last_key"), F.col("m.doc_id").alias("last_id"))
    plan = filled.join(cut, F.col("source").eqNullSafe(F.col("s")), "left")
    # no document of the bin fits: all bins before it are still taken
    first_of_bin = F.shiftleft(F.col("bin"), 32 - BIN_BITS) - 1
    plan = plan.select("source", "source_size", "target", "whole", F.coalesce("last_key", first_of_bin, F.lit(-1)).cast("long").alias("last_key"), F.when(F.col("last_key").isNull(), F.lit(2**63 - 1)).otherwise(F.col("last_id")).alias("last_id"))
    return thin, ws.save(plan, "plan")


def beside(plan: DataFrame) -> DataFrame:
    """The plan as a side of a join with documents, where a source may hold most rows: broadcast while the sources are few enough."""
    return F.broadcast(plan) if measured(plan) <= BROADCAST_SOURCES else plan


def copies(whole: Column, key: Column, doc_id: Column, last_key: Column, last_id: Column) -> Column:
    """How often the mix takes a document."""
    d = F.coalesce(doc_id, F.lit(-(2**63)))
    return whole + ((key < last_key) | ((key == last_key) & (d <= last_id))).cast("long")


def mix(docs: DataFrame, **options) -> DataFrame:
    """doc_id, source, size, source_size, target, copies, taken a row a document."""
    thin, plan = mix_plan(docs, **options)
    plan = beside(plan).withColumnRenamed("source", "s")
    out = thin.join(plan, thin.source.eqNullSafe(plan.s)).withColumn("copies", copies(*[F.col(c) for c in ("whole", "key", "doc_id", "last_key", "last_id")]))
    return out.select("doc_id", "source", "size", "source_size", "target", "copies", (F.col("copies") * F.col("size")).alias("taken"))


def materialise(docs: DataFrame, seed: int = 7, **options) -> DataFrame:
    """docs with each row as often as the mix takes it; texts are not shuffled, a row needs only its source's line of the plan."""
    _, plan = mix_plan(docs, seed=seed, **options)
    plan = beside(plan).select(*[F.col(c).alias(f"_mix_{c}") for c in plan.columns])
    joined = docs.join(plan, docs["source"].cast("string").eqNullSafe(plan["_mix_source"]))
    n = copies(F.col("_mix_whole"), seeded_key(docs["doc_id"], seed), docs["doc_id"].cast("long"), F.col("_mix_last_key"), F.col("_mix_last_id"))
    return joined.withColumn("_mix_n", n.cast("int")).where("_mix_n > 0").withColumn("_mix_copy", F.explode(F.array_repeat(F.lit(1), F.col("_mix_n")))).select(*[docs[c] for c in docs.columns])


MIX_SQL = r"""
WITH d AS (
  SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::BIGINT AS size,
         ('0x' || substr(md5('7:' || coalesce(doc_id::VARCHAR, '')), 1, 8))::BIGINT AS key
  FROM documents),
s AS (SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source),
w AS (SELECT *, CASE (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 WHEN 0 THEN 5.0::DOUBLE WHEN 1 THEN 2.0::DOUBLE ELSE 1.0::DOUBLE END AS weight,
             2.0::DOUBLE * source_size AS cap FROM s),
l AS (SELECT *, (1.5::DOUBLE * sum(source_size) OVER () - coalesce(sum(cap) OVER b, 0)) / (sum(weight) OVER () - coalesce(sum(weight) OVER b, 0)) AS level
      FROM w WINDOW b AS (ORDER BY cap / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
f AS (SELECT *, min_by(level, cap / weight) FILTER (level * weight <= cap) OVER () AS final FROM l),
t AS (SELECT source, source_size, CASE WHEN final IS NULL THEN cap ELSE least(cap, final * weight) END AS target FROM f),
r AS (SELECT *, CASE WHEN source_size > 0 THEN floor(target / source_size)::BIGINT ELSE 0 END AS whole FROM t),
o AS (SELECT d.*, r.source_size, r.target, r.whole, r.target - r.whole * r.source_size AS rest,
             sum(d.size) OVER (PARTITION BY d.source ORDER BY d.key, d.doc_id RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS upto,
             sum(d.size) OVER (PARTITION BY d.source, d.key, d.doc_id) AS step
      FROM d JOIN r ON d.source IS NOT DISTINCT FROM r.source)
SELECT doc_id, size, source_size, target, ((whole + CASE WHEN 2 * upto - step <= 2 * rest THEN 1 ELSE 0 END) * size)::BIGINT AS taken FROM o
"""
