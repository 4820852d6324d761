"""The SQL surface: functions over arrays, a table function for windows, and views of the steps of a series."""

from __future__ import annotations

import warnings
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import PandasUDFType, pandas_udf, udtf

from wavemotif.functions.vectors import BREAKPOINTS
from wavemotif.operators import prep as P


VECTOR = T.ArrayType(T.DoubleType())


def _letters(alphabet: int = 4) -> str:
    cuts = " ".join(f"WHEN e < {c}D THEN '{'abcdef'[i]}'" for i, c in enumerate(BREAKPOINTS[alphabet]))
    return f"CASE {cuts} ELSE '{'abcdef'[len(BREAKPOINTS[alphabet])]}' END"


#: Functions in SQL itself, so that they stay in the JVM: name and signature, type, body.
FUNCTIONS = {
    "sq_dist(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>)": ("DOUBLE", "aggregate(zip_with(a, b, (p, q) -> (p - q) * (p - q)), 0D, (s, v) -> s + v)"),
    "sax_word(x ARRAY<DOUBLE>)": ("STRING", f"array_join(transform(x, e -> {_letters()}), '')"),
    "sax_mindist(a STRING, b STRING, w INT)": (
        "DOUBLE",
        "sqrt(w / length(a) * aggregate(sequence(1, length(a)), 0D, (s, i) -> s + power(CASE WHEN abs(ascii(substring(a, i, 1)) - ascii(substring(b, i, 1))) < 2 THEN 0D"
        f" ELSE element_at(array({', '.join(f'{c}D' for c in BREAKPOINTS[4])}), greatest(ascii(substring(a, i, 1)), ascii(substring(b, i, 1))) - 97)"
        f" - element_at(array({', '.join(f'{c}D' for c in BREAKPOINTS[4])}), least(ascii(substring(a, i, 1)), ascii(substring(b, i, 1))) - 96) END, 2)))",
    ),
}


@udtf(returnType=T.StructType([T.StructField("start", T.LongType()), T.StructField("win", VECTOR)]))
class ExplodeWindows:
    """explode_windows(values, w): the windows of w values of an array, in order. Null or short arrays have none."""

    def eval(self, values: list[float] | None, w: int) -> Iterator[tuple[int, list[float]]]:
        for i in range(len(values or ()) - w + 1):
            yield i, values[i : i + w]


def _medoid(vectors: pd.Series) -> list[float]:
    """The member of a group with the least sum of distances to the others; the first one of equals by value. Quadratic in the group."""
    x = np.array(sorted(map(tuple, vectors)), float)
    total = [float(np.sqrt(((x - v) ** 2).sum(axis=1)).sum()) for v in x]
    return x[int(np.argmin(np.round(total, 9)))].tolist()


with warnings.catch_warnings():  # a hint of a list is read as an iterator, so the kind is given
    warnings.simplefilter("ignore")
    medoid = pandas_udf(_medoid, VECTOR, PandasUDFType.GROUPED_AGG)


def register_sql(spark: SparkSession, series: DataFrame | None = None, w: int = 20, d: int = 10) -> None:
    """Temporary functions sq_dist, sax_word, sax_mindist, explode_windows, medoid; with a series also views series, reduced, candidates."""
    for head, (kind, body) in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURNS {kind} RETURN {body}")
    spark.udtf.register("explode_windows", ExplodeWindows)
    spark.udf.register("medoid", medoid)
    if series is not None:
        series.createOrReplaceTempView("series")
        P.reduced_windows(P.znormalize(series), w, d, None).createOrReplaceTempView("reduced")
        P.candidates(series, w, d).createOrReplaceTempView("candidates")


def profile_series(series: DataFrame) -> DataFrame:
    """A row a sensor and run: counts, moments, and how the values go with time. Runs of one step have no deviation."""
    v, t = F.col("v").cast("double"), F.col("t").cast("double")
    return series.groupBy("sensor", "series_id").agg(
        F.count("*").alias("n"), F.min("v").alias("lowest"), F.max("v").alias("highest"), F.avg(v).alias("mean"), F.stddev_pop(v).alias("dev_pop"), F.stddev_samp(v).alias("dev"),
        F.corr(v, t).alias("corr_t"), F.regr_slope(v, t).alias("slope_t"), F.skewness(v).alias("skew"), F.kurtosis(v).alias("kurt"),
    )
