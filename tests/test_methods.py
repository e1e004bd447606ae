"""Units without Spark, invariants, parity with DuckDB, and plans."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from strata.functions.points import PointSet
from strata.operators import assign, kdtree, labeling, localsolver, merge, subset
from strata.plans import kmeans, measures, operator_queries, queries  # noqa: F401
from tests.conftest import same

SMALL = ["scan_points", "fixture_gauss", "kd_region_exact", "kd_region_ties", "kd_planes_exact", "kd_depth", "label_axis", "label_random", "label_ragged_drop", "partition_random", "subset_candidates", "merge_min_asse", "merge_hierarchical", "subset_kmeans_flagship", "single_machine", "iter_kmeans_raw", "assign_join", "assign_cells", "sse", "coverage", "join_asof", "agg_cube", "win_rank_family", "stream_session", "edge_tree_small", "kd_region_widest", "merge_hierarchical_distributed", "w7_rounds", "rounds_per_subset", "cogroup_models", "udaf_asse", "w2_sse_6_subsets", "w14_labels", "edge_as_many_clusters_as_points"]


@pytest.mark.parametrize("name", SMALL)
def test_parity(spark, sf, duck, name):
    a, b = same(queries.QUERIES[name](spark, sf), duck, queries.ORACLES[name])
    assert a == b and a


def test_worked_example(spark, sf):
    """Eight points on a line, capacity two: regions of two, and two interleaved subsets."""
    ps = queries.ps_of(spark, sf, "line8")
    rows = labeling.by_axis(kdtree.build_exact(ps, kdtree.depth_for(8, 2))).collect()
    assert sorted((r.c0, r.region_id) for r in rows) == [(k, 4 + (k - 1) // 2) for k in range(1, 9)]
    assert sorted(r.c0 for r in rows if r.label == 1) == [1, 3, 5, 7]


def test_depth_rules():
    assert [kdtree.depth_for(3000, c) for c in (6, 12, 24, 47, 94)] == [9, 8, 7, 6, 5]
    assert kdtree.depth_for(5, 8) == 0
    with pytest.raises(ValueError):
        kdtree.depth_for(0, 4)
    with pytest.raises(ValueError):
        kdtree.depth_for(10, 4, regions=2)


@given(st.lists(st.tuples(st.integers(-50, 50), st.integers(-50, 50)), min_size=4, max_size=80), st.integers(1, 4))
@settings(max_examples=60, deadline=None)
def test_solvers_agree(points, k):
    x = np.array(points, float)
    c0 = x[:k].copy()
    base = localsolver.solve(x, c0, 20)
    for other in ("bounds", "kdfilter"):
        s = localsolver.solve(x, c0, 20, solver=other)
        assert np.array_equal(s.centroids, base.centroids) and np.array_equal(s.labels, base.labels)
    again = localsolver.solve(x, base.centroids, 1)
    assert again.d2.sum() <= base.d2.sum() + 1e-6


def test_empty_cluster_and_ties():
    x = np.array([[0.0], [2.0]])
    s = localsolver.solve(x, np.array([[1.0], [1.0], [99.0]]), 1)
    assert s.centroids.ravel().tolist() == [1.0, 1.0, 99.0]


def test_hierarchical_merging():
    c = np.array([[0.0], [1.0], [10.0], [11.0]])
    assert merge.hierarchical_array(c, 2).ravel().tolist() == [0.5, 10.5]
    assert np.array_equal(merge.hierarchical_array(c, 4), c)


def test_partition_is_whole(spark, sf):
    ps = queries.ps_of(spark, sf, "orders2d")
    regions = kdtree.build_exact(ps, 4)
    sizes = [r["count"] for r in regions.groupBy("region_id").count().collect()]
    n = ps.count()
    assert set(sizes) <= {n // 16, -(-n // 16)}
    lab = labeling.by_axis(regions, subsets=n // 16, ragged="proportional")
    assert tuple(measures.partition_check(ps.df, lab).first()) == (0, 0, 0)
    full = measures.coverage(labeling.by_axis(regions, subsets=n // 16, ragged="drop")).collect()
    assert all(r.regions == 16 == r.points for r in full)


def test_results_do_not_depend_on_partitions(spark, sf):
    ps = queries.ps_of(spark, sf, "orders2d")
    got = []
    for parts in (1, 7):
        own = PointSet(ps.df.repartition(parts), 2)
        lab = labeling.by_random(kdtree.build_exact(own, 4), 3)
        got.append(sorted(map(tuple, subset.solve(lab, kmeans.of_ids(own, (0, 1)), 2, 5).collect())))
    assert got[0] == got[1]


def test_plans(spark, sf):
    ps = queries.ps_of(spark, sf, "orders2d")
    c = np.array([[0.0, 0.0], [1e6, 100.0]])
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    literal = plan(assign.by_literal(ps, c))
    assert "Exchange" not in literal and "NestedLoop" not in literal
    assert "ReadSchema: struct<o_orderkey:bigint,o_totalprice:double,o_orderdate:timestamp_ntz>" in literal
    lab = ps.df.withColumn("label", F.pmod("point_id", F.lit(6)) + 1)
    assert plan(subset.solve(lab, c, 2, 3)).count("Exchange") == 1
    assert plan(kdtree.build_exact(ps, 3)).count("Exchange ") == 3  # one for each level
    assert "partial_sum" in plan(assign.sums(assign.by_literal(ps, c), ps.coords))


def test_bad_points_and_limits(spark):
    df = spark.createDataFrame([(1, 1.0), (2, float("nan")), (3, None)], "i long, x double")
    assert PointSet.from_df(df, "i", [F.col("x")], on_bad="drop").count() == 1
    with pytest.raises(Exception):
        PointSet.from_df(df, "i", [F.col("x")]).df.collect()
    few = PointSet.from_df(df.filter("i = 1"), "i", [F.col("x")])
    with pytest.raises(ValueError):
        kmeans.subset_kmeans(few, 2, np.zeros((2, 1)), capacity=4)


def test_tendencies(spark, sf):
    """Averages over seeds: a tree beats none where subsets are small."""
    ps = queries.ps_of(spark, sf, "gauss3k")
    c0 = kmeans.of_ids(ps, queries.INITIAL[1])
    n = ps.count()

    def error(partition, seed):
        r = kmeans.subset_kmeans(ps, 4, c0, regions=16, subsets=None, partition=partition, labels="random", seed=seed, max_iter=20, n=n) if partition == "tree" else None
        if r is None:
            cands = subset.solve(labeling.random_partition(ps.df, n // 16, seed), c0, 2, 20)
            return kmeans.sse(ps, merge.min_asse(cands, 2)).first()[0]
        return kmeans.sse(ps, r.centroids).first()[0]

    assert sum(error("tree", k) for k in range(3)) < sum(error("random", k) for k in range(3))


def test_whole_tables(spark, sf):
    """The general forms take every event, and agree with plain numpy."""
    n = spark.read.parquet(f"{sf}/events.parquet").count()
    assert n > 3000
    x = queries.ps_of(spark, sf, "gauss_events").df.orderBy("point_id").toPandas()
    d2 = localsolver.distances(x[["c0", "c1"]].to_numpy(float), queries._C)
    for how in ("predict", "assign_join", "assign_cells"):
        got = queries.QUERIES[f"{how}_all"](spark, sf).orderBy("point_id").toPandas()
        assert len(got) == n and (got.cluster_id.to_numpy() == d2.argmin(1)).all()
    assert queries.QUERIES["sse_all"](spark, sf).first()[0] == int(np.floor(d2.min(1)).sum())
    assert sum(r.points for r in queries.QUERIES["coverage_all"](spark, sf).collect()) == n
    one = localsolver.solve(x[["c0", "c1"]].to_numpy(float), kmeans.of_ids(queries.ps_of(spark, sf, "gauss_events"), queries.INITIAL[5]))
    got = queries.QUERIES["iter_kmeans_combined_all"](spark, sf).orderBy("cluster_id").select("c0", "c1").toPandas().to_numpy()
    assert one.converged and np.allclose(got, one.centroids)
    assert queries.QUERIES["merge_hierarchical_all"](spark, sf).count() == queries.QUERIES["merge_min_asse_all"](spark, sf).count() == 4


def test_real_tables_converge(spark, sf):
    """Every subset ends where one more round moves nothing, as plain numpy finds it, beyond the parity forms' rounds."""
    ps = queries.ps_of(spark, sf, "docs2d")
    c0 = kmeans.of_ids(ps, (0, 1, 2))
    lab = kmeans.labelled(ps, 4, 12, ragged="proportional").toPandas()
    got = queries.converged(spark, sf, "docs2d", 4, 12, (0, 1, 2))[1].toPandas().sort_values(["subset_id", "cluster_id"])
    assert got.converged.all() and got.rounds.max() > queries.T_REAL
    for label, group in lab.groupby("label"):
        x, c = group.sort_values("point_id")[["c0", "c1"]].to_numpy(float), c0
        for _ in range(500):
            near = ((x[:, None] - c[None]) ** 2).sum(2).argmin(1)
            new = np.array([x[near == k].mean(0) if (near == k).any() else c[k] for k in range(3)])
            if (new == c).all():
                break
            c = new
        assert np.allclose(got[got.subset_id == label][["c0", "c1"]].to_numpy(), c)
    for name in ("w14_documents", "subset_kmeans_flagship", "subset_kmeans_planes"):
        assert queries.QUERIES[f"{name}_converged"](spark, sf).count() == 3


def test_whole_embeddings(spark, sf):
    """All 64 values are coordinates, and a subset's centroids are those of plain numpy over them."""
    raw = {r.vec_id: np.floor(np.array(r.embedding, float) * 1_000_000) for r in spark.read.parquet(f"{sf}/embeddings.parquet").collect()}
    ps = queries.ps_of(spark, sf, "embed64")
    assert ps.d == 64 == max(map(len, raw.values()))
    lab = kmeans.labelled(ps, 4, 20, ragged="proportional").select("point_id", "label").toPandas()
    got = queries.converged(spark, sf, "embed64", 4, 20, (0, 1, 2))[1].toPandas().sort_values(["subset_id", "cluster_id"])
    for label in (1, 2, 20):
        x = np.array([raw[i] for i in sorted(lab[lab.label == label].point_id)])
        c = np.array([raw[i] for i in (0, 1, 2)])
        for _ in range(100):
            near = ((x[:, None] - c[None]) ** 2).sum(2).argmin(1)
            c = np.array([x[near == k].mean(0) if (near == k).any() else c[k] for k in range(3)])
        assert np.allclose(got[got.subset_id == label][[f"c{k}" for k in range(64)]].to_numpy(), c)
    assert len(queries.QUERIES["w12_embed64_converged"](spark, sf).columns) == 65


def test_grid_has_all_subset_counts(spark, sf):
    rows = queries.QUERIES["grid_sse"](spark, sf).collect()
    assert len(rows) == 30 and {r.subsets for r in rows} == {5, 11, 23, 46, 93}


@given(st.lists(st.lists(st.tuples(st.integers(-50, 50), st.integers(-50, 50)), min_size=5, max_size=30), min_size=1, max_size=12), st.sampled_from(["keep", "farthest"]), st.sampled_from(["max", "sum"]))
@settings(max_examples=40, deadline=None)
def test_many_at_once_is_each_alone(parts, empty, shift):
    """Solving many subsets in one pass gives every bit that solving each gives."""
    parts = [np.array(p, float) for p in parts]
    c0 = np.array([[0.0, 0.0], [0.0, 0.0], [40.0, 40.0]])
    c, labels, d2, rounds, converged = localsolver.solve_many(np.concatenate(parts), np.cumsum([0] + [len(p) for p in parts[:-1]]), c0, 15, 0.0, empty, shift)
    at = 0
    for k, x in enumerate(parts):
        s = localsolver.solve(x, c0, 15, 0.0, "plain", "direct", empty, shift)
        assert np.array_equal(s.centroids, c[k]) and (s.rounds, s.converged) == (rounds[k], converged[k])
        assert np.array_equal(s.labels, labels[at : at + len(x)]) and np.array_equal(s.d2, d2[at : at + len(x)])
        at += len(x)


def test_subsets_in_batches_of_any_size(spark, sf, monkeypatch):
    """Subsets that end within a batch or go on over several are solved whole, and one beyond the limit is refused."""
    ps = queries.ps_of(spark, sf, "orders2d")
    c0 = kmeans.of_ids(ps, (0, 1, 2))
    lab = labeling.random_partition(ps.df, 7)
    got = []
    for together in (100_000, 300):
        monkeypatch.setattr(subset, "TOGETHER", together)
        got.append(sorted(map(tuple, subset.solve(lab, c0, 2, slots=3).collect())))
    assert got[0] == got[1] and len(got[0]) == 21
    monkeypatch.setattr(subset, "TOGETHER", 10)
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "50")
    try:
        assert sorted(map(tuple, subset.solve(lab, c0, 2, slots=3).collect())) == got[0]
        with pytest.raises(Exception, match="ask for more subsets"):
            subset.solve(lab, c0, 2, slots=3, most_rows=60).collect()
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")


def test_sampled_planes_below_the_driver(spark, sf):
    """Lower levels cut by one task a region give a whole tree of nearly even leaves."""
    ps = queries.ps_of(spark, sf, "orders2d")
    planes = kdtree.build_planes_sampled(ps, 6, per_leaf=64, on_driver=512)
    assert sorted(r.node for r in planes.collect()) == list(range(1, 64))
    sizes = [r["count"] for r in kdtree.assign_region(ps, planes, 6).groupBy("region_id").count().collect()]
    assert len(sizes) == 64 and max(sizes) < 2 * ps.count() / 64


def test_merging_in_groups(spark):
    """Weighted means of points stay so over rounds of groups, and one group is plain merging."""
    rng = np.random.default_rng(3)
    centres = np.array([[0.0, 0.0], [100.0, 0.0], [0.0, 100.0]])
    rows = [(i, k, *map(float, centres[k] + rng.normal(size=2)), int(rng.integers(1, 9))) for i in range(40) for k in range(3)]
    cands = spark.createDataFrame(rows, "subset_id long, cluster_id int, c0 double, c1 double, members long")
    got = merge.hierarchical_grouped(cands, 3, 2, fan_in=15)
    x, w = np.array([r[2:4] for r in rows]), np.array([r[4] for r in rows], float)
    want = np.array([np.average(x[k::3], axis=0, weights=w[k::3]) for k in range(3)])
    order = [int(((got - c) ** 2).sum(1).argmin()) for c in want]
    assert sorted(order) == [0, 1, 2] and np.allclose(got[order], want)
    assert np.allclose(merge.hierarchical_distributed(cands.filter("subset_id < 4"), 3, 2, weighted=True), merge.hierarchical(cands.filter("subset_id < 4"), 3, 2, weighted=True))


def test_pairing_is_the_cheapest():
    import itertools

    rng = np.random.default_rng(4)
    for n in (1, 2, 5, 6):
        cost = rng.random((n, n))
        best = measures.cheapest_pairing(cost)
        assert sorted(best) == list(range(n))
        assert np.isclose(cost[np.arange(n), best].sum(), min(cost[np.arange(n), list(p)].sum() for p in itertools.permutations(range(n))))
    a = rng.random((60, 3))
    assert measures.centroid_match(a, a[::-1])[1] == 0


def test_costs_of_a_run(spark, sf):
    """The session's own records: the baseline takes a job's exchange for each round, the method a fixed number."""
    ps = queries.ps_of(spark, sf, "gauss3k")
    c0, n = kmeans.of_ids(ps, queries.INITIAL[1]), ps.count()
    got = {r.run: r for r in spark.createDataFrame(queries.cost_rows(spark, ps, 1, c0, 9), queries.COST_COLUMNS).collect()}
    method, raw, combined = got["method"], got["baseline"], got["baseline, combined"]
    assert raw.rounds == combined.rounds == raw.exchanges == combined.exchanges and method.exchanges < raw.rounds
    assert raw.rows_shuffled == n * raw.rounds and combined.rows_shuffled <= 4 * 8 * combined.rounds < method.rows_shuffled < raw.rows_shuffled
    assert method.bytes_moved < raw.bytes_moved and 1 <= method.sse / raw.sse < 1.01
    with measures.Costs(spark) as none:
        pass
    assert (none.jobs, none.stages, none.moved) == (0, 0, 0)


def test_errors_grow_with_subsets(spark, sf):
    """As published: more subsets, more error; the baseline and one machine agree."""
    one = lambda name: queries.QUERIES[name](spark, sf).first()[0]
    errors = [one(f"w2_sse_{m}_subsets") for m in (6, 23, 93)]
    assert one("w1_baseline_init1") <= errors[0] < errors[1] < errors[2] * 1.05
    assert one("w4_baseline") == one("w4_single_machine") <= one("w4_sse_58_subsets") < one("w4_sse_937_subsets")


@given(st.lists(st.tuples(st.integers(-4, 4), st.integers(-4, 4)), min_size=2, max_size=40), st.integers(1, 3), st.booleans())
@settings(max_examples=80, deadline=None)
def test_merging_takes_the_least_pair_each_time(points, k, weighted):
    """Against all pairs looked at anew in each step, ties included."""
    c, w = np.array(points, float) * 0.3, np.arange(1, len(points) + 1) % 4
    left = {i: (row, float(w[i])) for i, row in enumerate(c)}
    number = len(c)
    while len(left) > k:
        _, i, j = min((sum((a - b) * (a - b) for a, b in zip(left[i][0], left[j][0], strict=True)), i, j) for i in left for j in left if i < j)
        (a, u), (b, v) = left.pop(i), left.pop(j)
        left[number] = ((a * u + b * v) / (u + v) if weighted and u + v else (a + b) / 2, u + v)
        number += 1
    got, weight = merge.hierarchical_weighted(c, k, w, weighted)
    assert np.array_equal(got, np.array([left[i][0] for i in sorted(left)])) and weight.tolist() == [left[i][1] for i in sorted(left)]


def test_merging_thousands_is_quick():
    import time

    c = np.random.default_rng(5).normal(size=(merge.MOST_CANDIDATES, 2))
    began = time.process_time()
    assert merge.hierarchical_array(c, 4).shape == (4, 2)
    assert time.process_time() - began < 8


@pytest.mark.parametrize("axes", ["cycle", "widest", [1, 0, 0]])
def test_deep_trees_are_exact(spark, sf, axes, monkeypatch):
    """Top levels by planes and the others inside tasks give the regions of the level-by-level tree."""
    ps = queries.ps_of(spark, sf, "customer2d")
    want = {(r.point_id, r.region_id) for r in kdtree.build_exact(ps, 7, axes if axes != [1, 0, 0] else (1, 0, 0)).select("point_id", "region_id").collect()}
    for per_task in (200, 100_000):
        got = kdtree.build_deep(ps, 7, axes, per_task)
        assert {(r.point_id, r.region_id) for r in got.select("point_id", "region_id").collect()} == want
    monkeypatch.setattr(kmeans, "AUTO_EXACT", 100)
    monkeypatch.setattr(kdtree, "build_planes_exact", lambda *a, **k: pytest.fail("a level that a task can hold is cut by scans of all points"))
    assert kmeans.subset_kmeans(ps, 2, kmeans.of_ids(ps, (1, 2)), subsets=5, how="hierarchical").centroids.shape == (2, 2)


@pytest.mark.parametrize("kind", ["integers", "fractions", "equal", "far"])
def test_deep_trees_of_any_numbers(spark, kind, monkeypatch):
    """The cuts of the top levels are exact for fractions, equal values and wide ranges too, whether few or no rows may be looked
    through on the driver."""
    h, i = F.xxhash64("id"), F.col("id")
    c0, c1, point_id = {"integers": (h % 1000, i % 50, i), "fractions": (h % 1000 / 1000.0, i % 50 / 1e5, i), "equal": (F.lit(5).cast("long"), i % 3, h), "far": (F.when(i % 2 == 0, 0).otherwise(i * 1_000_000_007), i - 2**60, -i)}[kind]
    ps = PointSet(spark.range(2000).select(point_id.alias("point_id"), c0.alias("c0"), c1.alias("c1")), 2)
    want = {(r.point_id, r.region_id) for r in kdtree.build_exact(ps, 5).select("point_id", "region_id").collect()}
    for few in (100_000, 0):
        monkeypatch.setattr(kdtree, "LOOKED_THROUGH", few, raising=False)
        got = kdtree.build_deep(ps, 5, per_task=200)
        assert {(r.point_id, r.region_id) for r in got.select("point_id", "region_id").collect()} == want


def test_a_deep_tree_takes_few_jobs(spark, sf, monkeypatch):
    """A level is a count and a look at the rows of one bin, no more; points that are made are kept until the subsets are solved, and
    then given back, but not those that the caller keeps."""
    ps = queries.ps_of(spark, sf, "customer2d")
    top = (ps.count() // 100).bit_length()
    with measures.Costs(spark) as c:
        kdtree.build_deep(ps, 7, per_task=100)
    assert top >= 3 and c.jobs <= 5 * top + 6
    monkeypatch.setattr(kmeans, "AUTO_EXACT", 100)
    for kept in (False, True):
        if kept:
            ps.df.persist()
        r = kmeans.subset_kmeans(ps, 2, kmeans.of_ids(ps, (1, 2)), regions=16, asse="dist")
        assert ps.df.storageLevel.useMemory == kept
        r.release()
    ps.df.unpersist()


def test_one_machine_is_a_task(spark, sf, monkeypatch):
    """The points of one machine are held by a task, not by the driver, and its limit is a worker's."""
    import inspect

    import pyspark.sql.classic.dataframe as frames

    assert inspect.signature(kmeans.single_machine).parameters["most"].default == subset.MOST_ROWS >= 9_000_000
    ps = queries.ps_of(spark, sf, "gauss_events")
    x, c0 = ps.df.orderBy("point_id").select("c0", "c1").toPandas().to_numpy(float), kmeans.of_ids(ps, queries.INITIAL[1])
    want = localsolver.solve(x, c0)
    monkeypatch.setattr(frames.DataFrame, "toPandas", lambda self: pytest.fail("points on the driver"))
    got = kmeans.single_machine(ps, 4, c0)
    assert np.array_equal(got.centroids, want.centroids) and got.rounds == want.rounds
    monkeypatch.setattr(localsolver, "ROWS_AT_ONCE", 77)
    again = localsolver.solve(x, c0)
    assert np.array_equal(again.centroids, want.centroids) and np.array_equal(again.d2, want.d2)


def test_rounds_without_a_limit():
    """A row of points along which the centroids creep takes over 100 rounds, and ends converged."""
    x = np.arange(3000.0)[:, None]
    c0 = x[:8]
    assert not localsolver.solve(x, c0, 100).converged
    one = localsolver.solve(x, c0, None)
    assert one.converged and one.rounds > 100 and np.array_equal(localsolver.solve(x, one.centroids, 1).centroids, one.centroids)
    c, _, _, rounds, converged = localsolver.solve_many(np.concatenate([x, x[:9]]), np.array([0, len(x)]), c0, None)
    assert converged.all() and rounds[0] == one.rounds and np.array_equal(c[0], one.centroids)


@pytest.mark.parametrize("name", ["cost_model_jobs", "cost_model_merge", "cost_model_volume", "cost_model_width", "kd_depth", "udtf_plan", "gauss_source"])
def test_models_take_their_sizes_from_a_table(spark, sf, duck, name):
    df = queries.QUERIES[name](spark, sf)
    assert any(f.endswith((".parquet")) for f in df.inputFiles())
    a, b = same(df, duck, queries.ORACLES[name])
    assert a == b and a
