"""Accuracy, coverage and cost measures."""

from __future__ import annotations

import json
import math

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def coverage(labelled: DataFrame) -> DataFrame:
    """Regions that each subset has a point of; a stratified subset has one in all."""
    return labelled.groupBy("label").agg(F.count_distinct("region_id").alias("regions"), F.count("*").alias("points"))


def region_balance(regions: DataFrame) -> DataFrame:
    return regions.groupBy("region_id").agg(F.count("*").alias("points")).groupBy("points").agg(F.count("*").alias("regions"))


def subset_sizes(labelled: DataFrame) -> DataFrame:
    return labelled.groupBy("label").agg(F.count("*").alias("points"))


def cluster_profile(predicted: DataFrame) -> DataFrame:
    return predicted.groupBy("cluster_id").agg(F.count("*").alias("points"), F.sum(F.floor("dist2")).alias("sse"))


def purity(predicted: DataFrame, truth: str = "truth") -> DataFrame:
    """Share of points in their cluster's most frequent true class."""
    n = predicted.groupBy("cluster_id", truth).agg(F.count("*").alias("n"))
    return n.groupBy("cluster_id").agg(F.max("n").alias("most"), F.sum("n").alias("all")).agg((F.sum("most") / F.sum("all")).alias("purity"))


def cheapest_pairing(cost: np.ndarray) -> list[int]:
    """For each row its column, of least total cost, by shortest augmenting paths: cubic in the number of rows."""
    n = len(cost)
    row_price, col_price = np.zeros(n + 1), np.zeros(n + 1)
    row_of = np.zeros(n + 1, int)  # by column; column 0 is where a search starts
    for row in range(1, n + 1):
        row_of[0], col = row, 0
        slack, came, done = np.full(n + 1, np.inf), np.zeros(n + 1, int), np.zeros(n + 1, bool)
        while row_of[col]:
            done[col] = True
            here = row_of[col]
            open_ = np.flatnonzero(~done[1:]) + 1
            reach = cost[here - 1, open_ - 1] - row_price[here] - col_price[open_]
            better = reach < slack[open_]
            slack[open_[better]], came[open_[better]] = reach[better], col
            following = open_[np.argmin(slack[open_])]
            step = slack[following]
            row_price[row_of[done]] += step
            col_price[done] -= step
            slack[~done] -= step
            col = following
        while col:
            row_of[col] = row_of[came[col]]
            col = came[col]
    out = [0] * n
    for col in range(1, n + 1):
        out[row_of[col] - 1] = col - 1
    return out


def centroid_match(a: np.ndarray, b: np.ndarray) -> tuple[list[int], float]:
    """The pairing of two sets of centroids with the least total distance, and the largest distance in it."""
    d = np.sqrt(((a[:, None, :] - b[None, :, :]) ** 2).sum(2))
    best = cheapest_pairing(d)
    return best, float(max(d[i, j] for i, j in enumerate(best)))


def rank_combinations(grid: DataFrame) -> DataFrame:
    return grid.withColumn("place", F.rank().over(Window.partitionBy("subsets").orderBy("sse")))


def tradeoff(runs: DataFrame) -> DataFrame:
    """Time saved and error added against the run of fewest subsets."""
    w = Window.orderBy("subsets")  # a handful of runs
    return runs.withColumn("time_ratio", F.col("ms") / F.first("ms").over(w)).withColumn("sse_ratio", F.col("sse") / F.first("sse").over(w))


def partition_check(points: DataFrame, labelled: DataFrame) -> DataFrame:
    """Counts of points lost, invented and doubled by a partition; all should be none."""
    lost = points.join(labelled, "point_id", "left_anti").count()
    new = labelled.join(points, "point_id", "left_anti").count()
    twice = labelled.groupBy("point_id").count().filter("count > 1").count()
    return points.sparkSession.createDataFrame([(lost, new, twice)], "lost long, invented long, doubled long")


# Closed forms of cost.


def model_jobs(n: int, capacity: int, rounds: int) -> tuple[int, int]:
    """Full exchanges of the data: of the method (levels, labelling, solving) and of the baseline (one per round)."""
    return max(0, math.ceil(math.log2(n / capacity))) + 2, rounds


def model_merge(k: int, m: int) -> tuple[int, int]:
    """Candidate comparisons: cubic for hierarchical merging, linear for the least average error."""
    return (k * m) ** 3, k * m


def model_volume(n: int, depth: int, rounds: int, k: int, partitions: int) -> dict[str, int]:
    """Rows shuffled."""
    return {"method_exact": n * (depth + 2), "method_planes": 2 * n, "baseline_raw": n * rounds, "baseline_combined": k * partitions * rounds}


class Costs:
    """What Spark did inside a `with` block, from the session's own status store: jobs, stages, tasks, bytes and time.

    `moved` is all bytes read, written, shuffled and spilled; the shares of time say where it went."""

    def __init__(self, spark):
        self.sc = spark.sparkContext
        self.jvm = self.sc._jvm
        self.store = self.sc._jsc.sc().statusStore()

    def _seen(self, kind) -> int:
        return max((x.jobId() if kind == "job" else x.stageId() for x in self._list(kind)), default=-1)

    def _list(self, kind):
        self.sc._jsc.sc().listenerBus().waitUntilEmpty()
        none = self.jvm.java.util.ArrayList()
        found = self.store.jobsList(none) if kind == "job" else self.store.stageList(none, False, False, self.sc._gateway.new_array(self.jvm.double, 0), none)
        return [found.apply(k) for k in range(found.size())]

    def __enter__(self):
        import time

        self.jobs_before, self.stages_before, self.began = self._seen("job"), self._seen("stage"), time.perf_counter()
        return self

    def __exit__(self, *_):
        import time

        self.ms = int(1000 * (time.perf_counter() - self.began))
        self.jobs = sum(x.jobId() > self.jobs_before for x in self._list("job"))
        own = [x for x in self._list("stage") if x.stageId() > self.stages_before and x.status().toString() == "COMPLETE"]
        self.stages, self.exchanges = len(own), sum(x.shuffleWriteBytes() > 0 for x in own)
        add = lambda name: int(sum(getattr(x, name)() for x in own))
        self.tasks, self.run_ms = add("numCompleteTasks"), add("executorRunTime")
        self.input_bytes, self.output_bytes, self.shuffle_write, self.shuffle_read, self.spill = map(add, ("inputBytes", "outputBytes", "shuffleWriteBytes", "shuffleReadBytes", "diskBytesSpilled"))
        self.shuffle_rows, self.start_ms, self.gc_ms, self.wait_ms = add("shuffleWriteRecords"), add("executorDeserializeTime"), add("jvmGcTime"), add("shuffleFetchWaitTime")
        self.moved = self.input_bytes + self.output_bytes + self.shuffle_write + self.shuffle_read + self.spill


def ledger(events_path: str) -> list[dict]:
    """Per stage of an uncompressed event log: tasks, milliseconds, bytes read, shuffled and spilled."""
    stages: dict[int, dict] = {}
    with open(events_path, encoding="utf-8") as f:
        for line in f:
            e = json.loads(line)
            if e["Event"] == "SparkListenerTaskEnd" and e.get("Task Metrics"):
                m = e["Task Metrics"]
                s = stages.setdefault(e["Stage ID"], {"stage": e["Stage ID"], "tasks": 0, "ms": 0, "bytes_read": 0, "bytes_written": 0, "shuffle_write": 0, "shuffle_read": 0, "shuffle_rows": 0, "spill": 0, "fetch_wait_ms": 0, "busy_tasks": 0})
                r, w = m["Shuffle Read Metrics"], m["Shuffle Write Metrics"]
                for key, v in (("tasks", 1), ("ms", m["Executor Run Time"]), ("bytes_read", m["Input Metrics"]["Bytes Read"]), ("bytes_written", m["Output Metrics"]["Bytes Written"]), ("shuffle_write", w["Shuffle Bytes Written"]), ("shuffle_rows", w["Shuffle Records Written"]), ("shuffle_read", r["Remote Bytes Read"] + r["Local Bytes Read"]), ("spill", m["Disk Bytes Spilled"]), ("fetch_wait_ms", r["Fetch Wait Time"]), ("busy_tasks", int(r["Total Records Read"] > 0))):
                    s[key] += v
    return list(stages.values())
