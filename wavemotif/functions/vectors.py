"""Column builders over arrays of doubles, and the algebra of clustering features (n, vector sum, squared sum)."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

# fixed values: Gaussian breakpoints of equal probability by alphabet size
BREAKPOINTS = {3: (-0.43, 0.43), 4: (-0.67, 0.0, 0.67), 5: (-0.84, -0.25, 0.25, 0.84), 6: (-0.97, -0.43, 0.0, 0.43, 0.97)}


def sq_dist(a: str | Column, b: str | Column, d: int) -> Column:
    """Squared Euclidean distance, written out so that it compiles to straight code."""
    a, b = (F.col(x) if isinstance(x, str) else x for x in (a, b))
    total = F.lit(0.0)
    for i in range(d):
        total = total + (a[i] - b[i]) * (a[i] - b[i])
    return total


def dot(a: Column, weights: list[float]) -> Column:
    total = F.lit(0.0)
    for i, w in enumerate(weights):
        total = total + a[i] * F.lit(float(w))
    return total


def sax_word(x: Column, d: int, alphabet: int = 4) -> Column:
    """A letter for each element, by the Gaussian breakpoints."""
    cuts = BREAKPOINTS[alphabet]

    def letter(e: Column) -> Column:
        out = F.lit("abcdef"[len(cuts)])
        for i in range(len(cuts) - 1, -1, -1):
            out = F.when(e < cuts[i], "abcdef"[i]).otherwise(out)
        return out

    return F.concat(*[letter(x[i]) for i in range(d)])


def fixed_planes(sets: int, per_set: int, d: int, seed: int = 20) -> list[list[list[int]]]:
    """Normals of random hyperplanes, [set][plane][dimension]: seeded Gaussian directions without mean (vectors have none either), in
    thousandths, so that every engine reads the same integers."""
    x = np.random.default_rng(seed).normal(size=(sets, per_set, d))
    if d > 1:
        x = x - x.mean(axis=2, keepdims=True)
    return np.round(1000 * x).astype(int).tolist()


def bucket_key(x: Column, planes: list[list[int]], family: str = "sign", width: float = 4.0) -> Column:
    """A text key of one set: sides of the planes, or cells along their normals. Cells as wide as vectors are long only tell the sides."""
    if family == "sign":
        return F.concat(*[F.when(dot(x, p) >= 0, "1").otherwise("0") for p in planes])
    return F.concat_ws("_", *[F.floor(dot(x, p) / F.lit(width * float(sum(e * e for e in p)) ** 0.5)).cast("string") for p in planes])


def cf_of(x: Column, d: int) -> Column:
    """The clustering feature of one vector."""
    return F.struct(F.lit(1).cast("long").alias("n"), x.alias("ls"), sum((x[i] * x[i] for i in range(1, d)), x[0] * x[0]).alias("ss"))


def cf_sum(x: Column, d: int) -> Column:
    """Aggregate: the clustering feature of a group of vectors; partial sums combine before a shuffle."""
    return F.struct(F.count("*").alias("n"), F.array(*[F.sum(x[i]) for i in range(d)]).alias("ls"), sum((F.sum(x[i] * x[i]) for i in range(1, d)), F.sum(x[0] * x[0])).alias("ss"))


def cf_merge(a: Column, b: Column) -> Column:
    return F.struct((a["n"] + b["n"]).alias("n"), F.zip_with(a["ls"], b["ls"], lambda x, y: x + y).alias("ls"), (a["ss"] + b["ss"]).alias("ss"))


def cf_centroid(cf: Column) -> Column:
    return F.transform(cf["ls"], lambda x: x / cf["n"])


def cf_radius(cf: Column) -> Column:
    """Root mean squared distance of the members from their centroid."""
    return F.sqrt(F.greatest(F.lit(0.0), cf["ss"] / cf["n"] - F.aggregate(cf["ls"], F.lit(0.0), lambda a, x: a + (x / cf["n"]) * (x / cf["n"]))))


def adjusted_radius(w: int, base: float = 1.0) -> float:
    return base if w <= 20 else base * (w / 20) ** 0.5


def adjusted_radius_of(w: str, base: float = 1.0) -> Column:
    """adjusted_radius for a column of lengths."""
    return F.when(F.col(w) > 20, base * F.sqrt(F.col(w) / 20)).otherwise(base)
