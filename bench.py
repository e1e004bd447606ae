"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

Per run: rows, depth, subsets, rounds, median seconds, the error's ratio to one machine, and
what the session's status store says of one more run: jobs, exchanges, bytes moved and rows
shuffled, with their ratios to the baseline that sends every point to a reducer each round.
"""

from __future__ import annotations

import json
import os
import statistics
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

SF_DIR, CPUS = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
RUNS = int(os.environ.get("BENCH_RUNS", "3"))


def timed(f):
    """The median of some runs after one to warm up, and the last result. No run finds what another has cached."""
    took = []
    for _ in range(1 + RUNS):
        t = time.perf_counter()
        out = f()
        took.append(time.perf_counter() - t)
        if hasattr(out, "release"):
            out.release()
    return statistics.median(took[1:]), out


def main() -> None:
    spark = SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    from strata.plans import kmeans, measures
    from strata.plans.queries import QUERIES, ps_of
    from strata.sources.fixtures import INITIAL

    times: dict[str, float] = {}
    runs = []

    def noted(name, f, **about):
        """Times a run, and counts what one more of it costs."""
        s, r = timed(f)
        with measures.Costs(spark) as c:
            f().release()
        times[name] = round(s, 3)
        runs.append({"run": name, **about, "rounds": r.rounds or None, "sec": round(s, 3), "sse_ratio": round(kmeans.sse(ps, r.centroids).first()[0] / least, 5), "jobs": c.jobs, "exchanges": c.exchanges, "bytes_moved": c.moved, "rows_shuffled": c.shuffle_rows})

    for fixture, depths in (("gauss3k", (9, 7, 5)), ("gauss15k", (8, 6, 4))):
        ps = ps_of(spark, SF_DIR, fixture)
        ps = type(ps)(ps.df.persist(), ps.d)
        n = ps.count()
        init = kmeans.of_ids(ps, INITIAL[1])
        one = kmeans.single_machine(ps, 4, init)
        least = kmeans.sse(ps, one.centroids).first()[0]
        for combine in (True, False):
            noted(f"{fixture}_rounds_{'combined' if combine else 'raw'}", lambda combine=combine: kmeans.iterative_kmeans(ps, 4, init, combine=combine), n=n)
        raw = runs[-1]
        for depth in depths:
            noted(f"{fixture}_subsets_{n >> depth}", lambda depth=depth: kmeans.subset_kmeans(ps, 4, init, regions=1 << depth, tree="sampled" if n > 100_000 else "exact", n=n), n=n, depth=depth, subsets=n >> depth)
            runs[-1] |= {f"{x}_ratio": round(runs[-1][x] / raw[x], 4) for x in ("sec", "jobs", "bytes_moved", "rows_shuffled")}
        ps.df.unpersist()
    for name in ("assign_literal", "assign_cells", "kd_region_ties", "w9_lineitem"):
        s, _ = timed(lambda: QUERIES[name](spark, SF_DIR).agg(F.count("*")).collect())
        times[name] = round(s, 3)
    print(json.dumps({"metric": "sum of median seconds of the headline queries", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": SF_DIR.rsplit("sf", 1)[-1], "runs": runs}))


if __name__ == "__main__":
    main()
