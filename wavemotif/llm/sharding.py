"""A reproducible shuffle into shards: a Feistel permutation of global row numbers, with cycle walking.

Rows are numbered in an order that depends on their content alone (a hash bin, then doc_id, the
checksum and size of the text, and a hash of the columns kept), so neither partitioning nor a second run moves a row. Bins are counted, their
counts summed over bins, and rows numbered within a bin: no task sorts more than a bin. An unbalanced Feistel network
permutes the smallest power of two that holds all numbers; values beyond the last number are walked through the
network until they fall inside. Then shard = value mod shards and slot = value div shards: shard sizes are at most
one apart, slots have no gap, and a row's place can be computed from its number alone.

DataFrame functions only. Defined cases: null text has 0 bytes and checksum 0; null doc_ids sort first;
repeated rows get different places (they share a bin, and so a task); an empty table gives an empty result; further columns are kept or not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from wavemotif.llm.common import Workspace, measured

BINS = 4096
WALK = 64
#: Odd multipliers under 2**31, a round key each.
ROUND = ((1_640_531_527, 374_761_393), (1_103_515_245, 668_265_263), (1_812_433_253, 1_274_126_177), (1_566_083_941, 951_274_213), (1_597_334_677, 2_024_237_689), (1_274_126_177, 1_103_515_245))


def _rounds(bits: int, seed: int) -> list[tuple[int, int, int]]:
    """(summand, multiplier, width of the half that is masked) a round."""
    low = bits // 2
    return [((k ^ (seed * 2_654_435 + i)) % 65_521, m, bits - low if i % 2 == 0 else low) for i, (m, k) in enumerate(ROUND)]


def _mask(product: Column, width: int) -> Column:
    folded = product.bitwiseXOR(F.shiftright(product, 17)).bitwiseAND((1 << 48) - 1)
    return F.shiftright(folded * 10_007, 9).bitwiseAND((1 << width) - 1)


def feistel(x: Column, bits: int, seed: int) -> Column:
    """A permutation of 0 .. 2**bits - 1 as one expression. Halves take turns to be masked with a mix of the other one.

    Each value is bound once, so the expression grows by a round and does not double with it.
    """
    low_bits = bits // 2
    rounds = _rounds(bits, seed)

    def bind(value: Column, then) -> Column:
        return F.element_at(F.transform(F.array(value), then), 1)

    def after(i: int, low: Column, high: Column) -> Column:
        if i == len(rounds):
            return F.shiftleft(high, low_bits).bitwiseOR(low)
        summand, m, width = rounds[i]
        source, other = (low, high) if i % 2 == 0 else (high, low)
        fresh = lambda p: other.bitwiseXOR(_mask(p, width))
        return bind((source + summand) * m, lambda p: bind(fresh(p), lambda v: after(i + 1, low, v) if i % 2 == 0 else after(i + 1, v, high)))  # source < 2**31: the product fits 63 bits

    return bind(x, lambda v: after(0, v.bitwiseAND((1 << low_bits) - 1), F.shiftright(v, low_bits)))


def with_feistel(rows: DataFrame, name: str, bits: int, seed: int) -> DataFrame:
    """rows with the same permutation of column name, a projection a step: compiled, and short in the plan."""
    low_bits, x = bits // 2, F.col(name)
    rows = rows.withColumns({"_low": x.bitwiseAND((1 << low_bits) - 1), "_high": F.shiftright(x, low_bits)})
    for i, (summand, m, width) in enumerate(_rounds(bits, seed)):
        source, other = ("_low", "_high") if i % 2 == 0 else ("_high", "_low")
        rows = rows.withColumn("_product", (F.col(source) + summand) * m)
        rows = rows.withColumn(other, F.col(other).bitwiseXOR(_mask(F.col("_product"), width)))
    return rows.withColumn("_next", F.shiftleft("_high", low_bits).bitwiseOR(F.col("_low"))).drop("_low", "_high", "_product")


def permute(rows: DataFrame, number: str, n: int, seed: int, compiled: int = 3) -> DataFrame:
    """rows with at: a permutation of 0 .. n - 1 of the column number.

    The domain is under twice n, so a step leads inside with a chance of a half at least. The first steps are projections; the few
    rows that are still outside walk on in one expression, and a walk over WALK steps ends but for a chance of 2**-64, which raises an error.
    """
    bits = max(2, (n - 1).bit_length())
    rows = with_feistel(rows.withColumn("at", F.col(number)), "at", bits, seed).drop("at").withColumnRenamed("_next", "at")
    for _ in range(compiled - 1):
        rows = with_feistel(rows, "at", bits, seed).withColumn("at", F.when(F.col("at") < n, F.col("at")).otherwise(F.col("_next"))).drop("_next")
    walk = F.aggregate(F.sequence(F.lit(1), F.lit(WALK)), F.col("at"), lambda acc, _: F.when(acc < n, acc).otherwise(feistel(acc, bits, seed)))
    walk = F.when(F.col("at") < n, F.col("at")).otherwise(walk)
    return rows.withColumn("at", walk).withColumn("at", F.when(F.col("at") < n, F.col("at")).otherwise(F.raise_error(F.lit("cycle walk did not end")).cast("long")))


def number_rows(rows: DataFrame, ws: Workspace, order: list[str]) -> tuple[DataFrame, DataFrame]:
    """(rows with number long: 0 .. n - 1, fixed by the columns of order; the saved rows). rows has no column bin or number."""
    binned = ws.save(rows.withColumn("bin", F.pmod(F.xxhash64(*order), F.lit(BINS))), "binned")
    counts = binned.groupBy("bin").agg(F.count("*").alias("c"))
    base = counts.select("bin", (F.sum("c").over(Window.orderBy("bin")) - F.col("c")).alias("base"))  # BINS rows at most
    inner = F.row_number().over(Window.partitionBy("bin").orderBy(*order))
    return binned.withColumn("inner", inner).join(F.broadcast(base), "bin").select(*rows.columns, (F.col("base") + F.col("inner") - 1).alias("number")), binned


def shard(docs: DataFrame, shards: int = 24, seed: int = 11, keep: list[str] | None = None) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard a row of docs; then the columns named in keep."""
    ws = Workspace(docs.sparkSession)
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    rest = F.xxhash64(*[F.col(c) for c in keep]) if keep else F.lit(0)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), rest.alias("_rest"), (F.octet_length(text) + 8).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), *[F.col(c).alias(f"_kept_{c}") for c in keep or ()])
    numbered, binned = number_rows(rows, ws, ["doc_id", "text_crc32", "size", "_rest"])
    out = permute(numbered, "number", max(1, measured(binned)), seed)
    return out.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), F.pmod("at", F.lit(shards)).cast("int").alias("shard"), F.floor(F.col("at") / shards).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"), *[F.col(f"_kept_{c}").alias(c) for c in keep or ()])
