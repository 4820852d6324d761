"""Times the headline queries and prints one line of JSON. BENCH_SF_DIR and BENCH_CPUS choose table folder and cores."""

import json
import os
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F


def headline():
    from wavemotif.operators import cluster as C
    from wavemotif.operators import prep as P
    from wavemotif.plans import pipeline as PL
    from wavemotif.sources import views as V

    def fleet_candidates(s, d):
        return P.candidates(V.fleet_view(s, d), 20, 10)

    def planted_candidates(s, d):
        return P.candidates(V.planted_view(s, d), 20, 10)

    def few(s, d, n=100):
        return V.planted_view(s, d).where(F.col("series_id") <= n)

    return {
        "fleet_view": V.fleet_view,
        "fleet_candidates_six_sensors": fleet_candidates,
        "planted_candidates": planted_candidates,
        "cftree_per_run": lambda s, d: C.cluster(planted_candidates(s, d), 1.0, "cftree", group=("sensor", "series_id")),
        "motifs_cftree_100_runs": lambda s, d: PL.discover(few(s, d), 20, 85).occurrences,
        "motifs_hash_100_runs": lambda s, d: PL.discover(few(s, d), 20, 85, method="hash", family="quantised", sets=10, per_set=8).occurrences,
        "text_candidates": lambda s, d: P.candidates(V.text_view(s, d), 20, 10),
    }


def main():
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "12g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    took = {}
    for name, f in headline().items():
        began = time.time()
        f(spark, sf).write.format("noop").mode("overwrite").save()
        took[name] = round(time.time() - began, 3)
    print(json.dumps({"metric": "headline_total", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": os.path.basename(sf.rstrip("/")).removeprefix("sf")}))
    spark.stop()


if __name__ == "__main__":
    main()
