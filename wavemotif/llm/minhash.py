"""Near-duplicate documents by min-max hashing.

One permutation of the shingle hashes gives two signature values, its minimum and its maximum, so a
signature of 2m values costs m hash evaluations; both agree between two sets with the probability of
their Jaccard similarity and the pair has less variance than two minima of one permutation. Bands of
the signature choose candidates, and every link is confirmed on the full shingle sets.

Plan: documents with the same set of shingles become one representative. Representatives meet in
band buckets. The members that share most buckets with others come first, as what copies were made from does. Each member is compared with the first
of its bucket, one comparison a member, which joins groups of copies. In the few buckets that still hold more than one
component, the members of different components are compared in blocks of BLOCK: bitmaps of the sets bound what two of
them can share, pairs below the bound are left out, the others are compared exactly, and only links that join
components leave the task. So no pair of candidates in different components goes untested, none are emitted as rows, and a
task holds two blocks. Passes exchange ids; shingle sets are written once, for candidates only.

Equality of shingles is by 64-bit hashes, that of sets by their size and two sums of 64 bits.

Defined cases: null or empty text has no shingles, is alone and kept. Repeated rows and equal texts
share a component; texts that share a doc_id are told apart. Rows with a null doc_id get a null component and are kept. An empty table gives an empty
result. Further columns are not read.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from wavemotif.llm.common import Workspace, WordHashes, anti_by_id, connected_components, documents, map_batches, measured, mix64, semi_by_id, shingle_hashes, utf8

#: Members of a bucket that a task compares with as many others.
BLOCK = 512
BITMAP = 4096
#: Columns that tell equal sets, and the number of parts that a group of them is split into.
SAME = ["hi", "lo", "n_shingles"]
PARTS = 4096
SIGNATURE_SCHEMA = "doc_id long, n_shingles long, hi long, lo long, bands array<long>"


def choose_bands(threshold: float, miss: float = 1e-6, values: int = 200) -> tuple[int, int]:
    """(rows, bands): the longest bands for which a pair at the threshold is missed with probability miss at most."""
    best = (1, max(1, math.ceil(math.log(miss) / math.log(1 - threshold + 1e-12))))
    for rows in range(2, 13):
        bands = math.ceil(math.log(miss) / math.log(1 - threshold**rows))
        if rows * bands <= values:
            best = (rows, bands)
    return best


class Signer:
    """Signatures of sets of shingle hashes."""

    def __init__(self, rows: int, bands: int, seed: int = 1):
        self.rows, self.bands = rows, bands
        m = (rows * bands + 1) // 2
        rng = np.random.default_rng(seed)
        self.multiplier = rng.integers(0, 2**63, m, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
        self.flip = rng.integers(0, 2**63, m, dtype=np.uint64)
        self.place = mix64(np.arange(1, rows + 1, dtype=np.uint64))
        self.band = mix64(np.arange(1001, 1001 + bands, dtype=np.uint64))

    def values(self, shingles: np.ndarray) -> np.ndarray:
        low = np.full(len(self.multiplier), np.iinfo(np.uint64).max, np.uint64)
        high = np.zeros(len(self.multiplier), np.uint64)
        for at in range(0, len(shingles), 2048):
            x = (shingles[None, at : at + 2048] ^ self.flip[:, None]) * self.multiplier[:, None]
            np.minimum(low, x.min(axis=1), out=low)
            np.maximum(high, x.max(axis=1), out=high)
        return np.stack([low, high], axis=1).ravel()

    def keys(self, shingles: np.ndarray) -> np.ndarray:
        """One 64-bit key a band."""
        v = mix64(self.values(shingles)[: self.rows * self.bands]).reshape(self.bands, self.rows)
        return mix64((v * (self.place | np.uint64(1))).sum(axis=1, dtype=np.uint64) ^ self.band).view(np.int64)


def _signatures(words: int, signer: Signer):
    cache = WordHashes()

    def fn(batch: pa.RecordBatch) -> pa.RecordBatch:
        n, hi, lo, keys, ends = [], [], [], [], [0]
        for text in utf8(batch):
            s = np.unique(shingle_hashes(cache.array(text.lower().split()), words))
            n.append(len(s))
            for to, d in zip((hi, lo), digests(s), strict=True):
                to.append(d)
            if len(s):
                keys.append(signer.keys(s))
            ends.append(ends[-1] + (signer.bands if len(s) else 0))
        flat = pa.array(np.concatenate(keys) if keys else np.empty(0, np.int64))
        return pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(n, pa.int64()), pa.array(hi, pa.int64()), pa.array(lo, pa.int64()), pa.ListArray.from_arrays(pa.array(ends, pa.int32()), flat)], ["doc_id", "n_shingles", "hi", "lo", "bands"])

    return fn


def digests(s: np.ndarray) -> tuple[int, int]:
    """Two sums over a set of hashes; with its size they stand for the set."""
    return int(s.sum(dtype=np.uint64).view(np.int64)), int(mix64(s ^ np.uint64(0xABCDEF0123456789)).sum(dtype=np.uint64).view(np.int64))


def _sets(words: int):
    cache = WordHashes()

    def fn(batch: pa.RecordBatch) -> pa.RecordBatch:
        sets = [np.unique(shingle_hashes(cache.array(text.lower().split()), words)) for text in utf8(batch)]
        hi, lo = zip(*map(digests, sets), strict=True) if sets else ((), ())
        ends = np.concatenate([[0], np.cumsum([len(s) for s in sets])]).astype(np.int32)
        flat = pa.array(np.concatenate([np.empty(0, np.int64), *[s.view(np.int64) for s in sets]]))
        return pa.RecordBatch.from_arrays([pa.array(hi, pa.int64()), pa.array(lo, pa.int64()), pa.array([len(s) for s in sets], pa.int64()), pa.ListArray.from_arrays(pa.array(ends), flat)], [*SAME, "shingles"])

    return fn


def _block_links(threshold_pct: int):
    """Links between components of members of two blocks of one bucket, as many as connect what is linked."""

    def fn(group: pa.Table) -> pa.Table:
        rep, comp, block, sets, bits, bands, here = _unpack(group)
        root = {c: c for c in comp.tolist()}

        def find(c: int) -> int:
            while root[c] != c:
                root[c] = c = root[root[c]]
            return c

        n = np.array([len(s) for s in sets])
        i0, j0 = group.column("i")[0].as_py(), group.column("j")[0].as_py()
        order = np.flatnonzero(block == i0)
        out = []
        for x in order:
            y = np.flatnonzero((block == j0) & ((rep > rep[x]) if i0 == j0 else True) & (comp != comp[x]) & (100 * np.minimum(n, n[x]) >= threshold_pct * np.maximum(n, n[x])))
            need = -(-threshold_pct * (n[x] + n[y]) // (100 + threshold_pct))
            y = y[n[x] - np.bitwise_count(bits[x] & ~bits[y]).sum(axis=1, dtype=np.int64) >= need]  # no less can be common
            y = y[(bands[y] == bands[x]).argmax(axis=1) == here] if len(y) else y  # a pair is tested in the first bucket that it shares
            for k in y.tolist():
                a, b = find(int(comp[x])), find(int(comp[k]))
                if a != b:
                    common = len(np.intersect1d(sets[x], sets[k], assume_unique=True))
                    if 100 * common >= threshold_pct * (n[x] + n[k] - common):
                        out.append((a, b))
                        root[max(a, b)] = min(a, b)
        return pa.table({"a": pa.array([a for a, _ in out], pa.int64()), "b": pa.array([b for _, b in out], pa.int64())})

    return fn


def _unpack(group: pa.Table) -> tuple:
    """Columns of a group as arrays, and a bitmap of each set: bits that one has and the other lacks bound what is common."""
    sets = [np.asarray(s, np.int64) for s in (x.values.to_numpy(zero_copy_only=False) for x in group.column("shingles"))]
    words = np.zeros((len(sets), BITMAP // 64), np.uint64)
    for k, s in enumerate(sets):
        mark = np.zeros(BITMAP, np.uint8)
        mark[s.view(np.uint64) & np.uint64(BITMAP - 1)] = 1
        words[k] = np.packbits(mark).view(np.uint64)
    bands = np.stack([x.values.to_numpy(zero_copy_only=False) for x in group.column("bands")])
    here = int((bands[0] == group.column("bucket")[0].as_py()).argmax())
    return group.column("rep").to_numpy(), group.column("comp").to_numpy(), group.column("block").to_numpy(), sets, words, bands, here


def near_duplicates(docs: DataFrame, threshold_pct: int = 80, words: int = 5, miss: float = 1e-6, seed: int = 1) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for every row of docs.

    Two documents are linked if 100 * |intersection| >= threshold_pct * |union| of their sets of words-word
    shingles (A-Z lower-cased, words cut at ASCII white space). A linked pair is missed with probability miss at
    most. component_id is the smallest doc_id reachable over links.
    """
    ws = Workspace(docs.sparkSession)
    docs = documents(docs)
    rows, bands = choose_bands(threshold_pct / 100, miss)
    signed = ws.save(map_batches(docs, _signatures(words, Signer(rows, bands, seed)), SIGNATURE_SCHEMA), "signed")
    keyed = signed.where("doc_id is not null and n_shingles > 0").withColumn("part", F.pmod(F.xxhash64("doc_id"), F.lit(PARTS)))
    # equal sets are never joined as a whole: a group is split into parts, and only a row a part meets the group's representative
    parted = keyed.groupBy(*SAME, "part").agg(F.min("doc_id").alias("least"))
    # a number stands for each set, so documents that share an id but not their text stay apart
    reps = ws.save(parted.groupBy(*SAME).agg(F.min("least").alias("least")).withColumn("rep", F.monotonically_increasing_id()), "reps")
    # of equal sets one row takes part in the search
    first = keyed.join(reps.withColumnRenamed("least", "doc_id"), [*SAME, "doc_id"]).dropDuplicates(["rep"])
    spread = first.select("rep", F.col("n_shingles").alias("n"), F.explode("bands").alias("bucket"))
    shared = spread.groupBy("bucket").agg(F.count("*").alias("c")).where("c > 1")
    members = ws.save(spread.join(shared, "bucket"), "members")
    popular = members.groupBy("rep").agg(F.sum("c").alias("popularity"))
    members = ws.save(members.drop("c").join(popular, "rep"), "members")
    searched = reps.join(members.select("rep").distinct(), "rep", "left_semi")
    ids = ws.save(searched.select(F.col("least").alias("doc_id")).distinct(), "candidates")
    sets = map_batches(semi_by_id(docs, ids, measured(ids)), _sets(words), "hi long, lo long, n_shingles long, shingles array<long>")
    sets = ws.save(sets.join(searched.select(*SAME, "rep"), SAME).select("rep", "shingles").dropDuplicates(["rep"]), "sets")
    # first pass: each member with the first of its bucket
    first_of = members.groupBy("bucket").agg(F.min(F.struct(-F.col("popularity"), "rep", F.col("n").alias("pn"))).alias("m")).select("bucket", F.col("m.rep").alias("p"), F.col("m.pn").alias("pn"))
    pairs = members.join(first_of, "bucket").where("rep <> p").where(100 * F.least("n", "pn") >= threshold_pct * F.greatest("n", "pn")).select("rep", "p", "n", "pn").distinct()
    pairs = pairs.join(sets.select("rep", F.col("shingles").alias("a")), "rep").join(sets.select(F.col("rep").alias("p"), F.col("shingles").alias("b")), "p")
    pairs = pairs.withColumn("i", F.size(F.array_intersect("a", "b"))).where(100 * F.col("i") >= threshold_pct * (F.col("n") + F.col("pn") - F.col("i")))
    links = ws.save(pairs.select(F.col("rep").alias("a"), F.col("p").alias("b")), "links")
    parts = ws.save(connected_components(links, ws), "parts")
    # second pass: buckets that still hold more than one component, all pairs of different components, in blocks
    at = members.join(parts, members.rep == parts.id, "left").select("bucket", "rep", F.coalesce("component", "rep").alias("comp"))
    rest = at.groupBy("bucket").agg(F.count("*").alias("c"), F.min("comp").alias("x"), F.max("comp").alias("y")).where("x <> y and c > 2").select("bucket", "c")
    rest = at.join(rest, "bucket").withColumn("block", F.floor((F.row_number().over(Window.partitionBy("bucket").orderBy("rep")) - 1) / BLOCK).cast("int"))
    others = F.transform(F.sequence(F.lit(0), F.floor((F.col("c") - 1) / BLOCK).cast("int")), lambda j: F.struct(F.least("block", j).alias("i"), F.greatest("block", j).alias("j")))
    rest = rest.select("bucket", "rep", "comp", "block", F.explode(others).alias("to")).select("bucket", "rep", "comp", "block", "to.i", "to.j")
    rest = rest.join(sets, "rep").join(first.select("rep", "bands"), "rep")
    more = ws.save(rest.groupBy("bucket", "i", "j").applyInArrow(_block_links(threshold_pct), "a long, b long"), "more")
    ws.drop(sets, members, ids)
    named = reps.join(parts.select(F.col("id").alias("rep"), "component"), "rep", "left").withColumn("component", F.coalesce("component", "rep"))
    if measured(more):
        joined = connected_components(more, ws).select(F.col("id").alias("component"), F.col("component").alias("wider"))
        named = named.join(joined, "component", "left").withColumn("component", F.coalesce("wider", "component")).drop("wider")
    name = named.groupBy("component").agg(F.min("least").alias("component_id"))
    classes = parted.select(*SAME, "part").join(named.join(name, "component").select(*SAME, "component_id"), SAME)
    alone = signed.where("doc_id is null or n_shingles = 0").select("doc_id", "n_shingles", F.col("doc_id").alias("component_id"))
    out = keyed.join(classes, [*SAME, "part"]).select("doc_id", "n_shingles", "component_id").unionByName(alone)
    return out.withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id")))


def drop_near_duplicates(docs: DataFrame, threshold_pct: int = 80, words: int = 5) -> DataFrame:
    """docs without the documents that are not the smallest id of their group; columns unchanged. An id with several texts goes if all of them do."""
    gone = near_duplicates(docs, threshold_pct, words).groupBy("doc_id").agg(F.max("kept").alias("kept")).where("not kept")
    return anti_by_id(docs, gone, Workspace(docs.sparkSession))
