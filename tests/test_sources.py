"""Files of points, labelled data and models; the event log's ledger; refits on streams."""

import json
import os

import numpy as np
import pytest
from pyspark.sql import functions as F

from strata.functions.points import PointSet
from strata.operators import kdtree, labeling
from strata.plans import kmeans, measures, operator_queries, queries  # noqa: F401
from strata.sources import files
from strata.streaming import events


@pytest.mark.parametrize("fmt", files.FORMATS)
def test_round_trip(spark, tmp_path, fmt):
    df = spark.createDataFrame([(1, 1.5, -2.0), (2, 0.0, 3.25)], "point_id long, c0 double, c1 double")
    path = str(tmp_path / fmt)
    if fmt == "text":
        df.select(F.concat_ws(" ", *df.columns)).write.text(path)
    else:
        df.write.format(fmt).save(path)
    back = files.read_points(spark, path, fmt, 2)
    assert sorted(map(tuple, back.df.collect())) == sorted(map(tuple, df.collect()))


def test_labelled_and_model(spark, sf, tmp_path):
    ps = queries.ps_of(spark, sf, "supplier1d")
    lab = labeling.by_axis(kdtree.build_exact(ps, 2))
    files.write_labelled(lab, str(tmp_path / "lab"))
    one = spark.read.parquet(str(tmp_path / "lab")).filter("label = 2")
    assert one.count() == 4 and "PartitionFilters: [isnotnull(label" in one._jdf.queryExecution().executedPlan().toString()
    c = np.array([[1.0, 2.0], [3.0, 4.0]])
    files.save_model(spark, c, str(tmp_path / "model"), rounds=3)
    back, about = files.load_model(spark, str(tmp_path / "model"))
    assert np.array_equal(back, c) and about == {"k": 2, "d": 2, "rounds": 3}


def test_ledger(tmp_path):
    metrics = {"Executor Run Time": 5, "Input Metrics": {"Bytes Read": 7}, "Output Metrics": {"Bytes Written": 0}, "Disk Bytes Spilled": 1, "Shuffle Write Metrics": {"Shuffle Bytes Written": 11, "Shuffle Records Written": 2}, "Shuffle Read Metrics": {"Remote Bytes Read": 3, "Local Bytes Read": 4, "Fetch Wait Time": 0, "Total Records Read": 9}}
    log = tmp_path / "log"
    log.write_text("".join(json.dumps({"Event": "SparkListenerTaskEnd", "Stage ID": 1, "Task Metrics": metrics}) + "\n" for _ in range(2)) + json.dumps({"Event": "SparkListenerJobStart"}))
    (s,) = measures.ledger(str(log))
    assert (s["tasks"], s["ms"], s["bytes_read"], s["shuffle_write"], s["shuffle_read"], s["busy_tasks"]) == (2, 10, 14, 22, 14, 2)


def test_refit_on_a_stream(spark, sf):
    c0, fitted = np.array([[100.0, 100.0], [9000.0, 60_000.0]]), []

    def fit(batch, number):
        p = events.points(batch)
        fitted.append(kmeans.iterative_kmeans(PointSet(p.df.select("point_id", "c0", "c1"), 2), 2, c0, max_iter=3).centroids)

    events.refit(events.stream(spark, sf), fit)
    batch = kmeans.iterative_kmeans(queries.ps_of(spark, sf, "events2d"), 2, c0, max_iter=3).centroids
    assert len(fitted) == 1 and np.array_equal(fitted[0], batch)


def test_late_rows_are_counted(spark, tmp_path):
    """Rows behind the watermark of the batch before are left out of the windows, and their number is known."""
    import os

    path = str(tmp_path / "in")
    for number, hours in enumerate(((1, 2, 3), (9, 10, 10), (10, 10, 11), (2, 10, 3))):
        rows = [(10 * number + k, f"2024-01-01 {h:02}:30:00", 1, "view", 20.0, "") for k, h in enumerate(hours)]
        one = str(tmp_path / f"f{number}")
        spark.createDataFrame(rows, "event_id long, ts string, user_id long, event_type string, value double, props string").withColumn("ts", F.col("ts").cast("timestamp_ntz")).coalesce(1).write.parquet(one)
        os.makedirs(path, exist_ok=True)
        (part,) = [x for x in os.listdir(one) if x.endswith(".parquet")]
        os.rename(f"{one}/{part}", f"{path}/{number}.parquet")
        os.utime(f"{path}/{number}.parquet", (1_700_000_000 + number, 1_700_000_000 + number))
    late = []
    c = np.array([[0.0, 0.0], [9000.0, 60_000.0]])
    scored = events.score(events.stream(spark, path, "*.parquet", 1), c)
    got = events.run_to_end(events.counts(scored, "1 hour", late="1 hour"), "late_test", "update", lambda q: late.append(events.late_rows(q))).collect()
    assert late == [2]
    counted = {}
    for r in got:
        counted[r.start_us, r.cluster_id] = max(r.n, counted.get((r.start_us, r.cluster_id), 0))
    assert sum(counted.values()) == 10


def test_a_stream_of_rows_ends_in_files(spark, sf):
    """Rows that are as many as the events go to files that executors write, and all of them are there."""
    got = queries.QUERIES["stream_dedup"](spark, sf)
    assert got.inputFiles() and all("/rows/" in f for f in got.inputFiles())
    assert sorted(r.event_id for r in got.collect()) == sorted(r.event_id for r in spark.read.parquet(f"{sf}/events.parquet").select("event_id").collect())
    none = events.deduplicated(events.stream(spark, sf).filter("event_id < 0")).select("event_id")
    assert events.run_to_end(none, "strata_no_rows_" + os.urandom(4).hex()).collect() == []


def test_scored_events_end_in_files(spark, sf, duck):
    """Every scored event is in the files, with the statement's cluster."""
    from tests.conftest import same

    got = queries.QUERIES["stream_score"](spark, sf)
    assert got.inputFiles() and all("/rows/" in f for f in got.inputFiles())
    a, b = same(got, duck, queries.ORACLES["stream_score"])
    assert a == b and a


@pytest.mark.parametrize("name", ["stream_session", "stream_tumbling", "stream_sliding", "stream_running_centroids", "stream_static_join"])
def test_whole_results_of_a_stream_end_in_files(spark, sf, duck, name):
    """A result that is given whole with each batch lies in files, and is the statement's."""
    from tests.conftest import same

    got = queries.QUERIES[name](spark, sf)
    assert got.inputFiles() and all("/rows/" in f for f in got.inputFiles())
    a, b = same(got, duck, queries.ORACLES[name])
    assert a == b and a
