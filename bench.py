"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one line of JSON."""

from __future__ import annotations

import json
import os
import sys
import time

HERE = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, HERE)
os.environ["PYTHONPATH"] = os.pathsep.join(filter(None, (HERE, os.environ.get("PYTHONPATH"))))  # for Python workers

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

WORKLOADS = ("d1", "d2", "d3")


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", str(2 * int(cpus)))
        .config("spark.driver.memory", "12g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")

    from simcluster.plans import evaluate as E
    from simcluster.plans import experiments as K
    from simcluster.plans.baselines import exhaustive_threshold
    from simcluster.plans.search import SimilarClusterSearch

    times: dict[str, float] = {}
    measures: dict[str, dict] = {}

    def timed(name: str, f):
        began = time.perf_counter()
        out = f()
        times[name] = round(time.perf_counter() - began, 2)
        return out

    budget = float(os.environ.get("BENCH_SECONDS", "900"))
    began = time.perf_counter()
    for work in WORKLOADS:
        if time.perf_counter() - began > budget:
            break
        prep = K.prepare(spark, sf_dir, work)
        timed(f"{work}_pairs", lambda prep=prep: prep.pairs.count())
        timed(f"{work}_clusters", lambda prep=prep: prep.total)
        timed(f"{work}_shapes", lambda prep=prep: prep.shapes.count())
        timed(f"{work}_features", lambda prep=prep: prep.features.count())
        out, rows = {}, {}
        for p in (0.1, 0.3, 0.5):
            def search(p=p, prep=prep):
                found = SimilarClusterSearch(p=p, r_d=0.9).run(prep)
                return found, found.result.count()

            out[p], rows[p] = timed(f"{work}_search_p{int(p * 100)}", search)
        timed(f"{work}_exhaustive", lambda prep=prep: prep.all_si.count())
        for p, found in out.items():
            truth = exhaustive_threshold(prep.all_si, found.tau).count()
            error = E.recall_error(found, prep.all_si, p)
            measures[f"{work}_p{int(p * 100)}"] = {"coverage": round(found.coverage, 4), "ratio": round(found.coverage / p, 3), "recall": round(rows[p] / truth, 4) if truth else 1.0, "recall_at_share": round(error["true"], 4), "recall_at_share_estimate": round(error["estimate"], 4), "tau": round(found.tau, 4), "threshold_error": round(E.threshold_error(prep.all_si, found.tau, p)["error"], 4)}
        sizes = prep.clusters.agg(F.count("*"), F.avg("size")).head()
        measures[work] = {"clusters": sizes[0], "mean_size": round(sizes[1], 2), "pair_similarities": prep.all_si.agg(F.sum("n_pairs")).head()[0]}
    print(json.dumps({"metric": "seconds of all headline queries", "value": round(sum(times.values()), 2), "unit": "sec", "queries": times, "sf": os.path.basename(sf_dir.rstrip("/")).removeprefix("sf"), "measures": measures}))
    spark.stop()


if __name__ == "__main__":
    main()
