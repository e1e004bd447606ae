"""A query for each method, variant, baseline, measure and workload, with its DuckDB statement where one exists."""

from __future__ import annotations

from collections.abc import Callable, Sequence

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from strata.functions import points as fn
from strata.functions.points import PointSet
from strata.operators import assign, kdtree, labeling, merge, subset
from strata.plans import kmeans, measures
from strata.plans.oracle import SSE, Chain, cols, dims
from strata.sources import fixtures
from strata.sources.fixtures import INITIAL

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}

#: Rounds of parity runs: enough for the mixtures to converge, a fixed number for real columns.
T_GAUSS, T_REAL = 30, 8


def query(name: str, sql: str | None = None):
    def put(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return put


def ps_of(spark: SparkSession, sf_dir: str, fixture: str) -> PointSet:
    if fixture in ("gauss3k", "gauss15k", "gauss_events"):
        return getattr(fixtures, fixture)(spark, sf_dir)
    return fn.featurized(spark, sf_dir, fixture)


def rows(spark: SparkSession, c: np.ndarray) -> DataFrame:
    """Centroids as cluster_id and c*."""
    return spark.createDataFrame([(k, *map(float, r)) for k, r in enumerate(c)], "cluster_id int, " + ", ".join(f"c{i} double" for i in range(c.shape[1])))


# Points.

for _f in ("orders2d", "events2d", "customer2d", "supplier1d", "part2d", "docs2d", "pages2d", "lineitem2d", "embed8"):
    query("scan_points" if _f == "orders2d" else f"featurize_{_f}", Chain(_f).select("SELECT * FROM p"))(lambda s, d, f=_f: ps_of(s, d, f).df)
query("fixture_gauss", Chain("gauss3k").select("SELECT * FROM p"))(lambda s, d: ps_of(s, d, "gauss3k").df)
query("fixture_gauss15k", Chain("gauss15k").select("SELECT * FROM p"))(lambda s, d: ps_of(s, d, "gauss15k").df)


@query("gauss_source", Chain("gauss_events").select("SELECT * FROM p"))
def gauss_source(s, d):
    """The source's points of all events: it makes those from the least to the largest id, and the events pick theirs."""
    s.dataSource.register(fixtures.GaussSource)
    ids = fn.table(s, d, "events").select(F.col("event_id").alias("point_id"))
    first, last = ids.agg(F.min("point_id"), F.max("point_id")).first()
    made = s.read.format("strata_gauss").option("first", first or 0).option("rows", 0 if last is None else last - first + 1).option("parts", 64).load()
    return made.join(ids.hint("merge"), "point_id")  # ids look small enough to broadcast, but are as many as the events


query("scale_minmax", Chain("customer2d").select("SELECT point_id, round(((c0 - a) / b::DOUBLE), 9) c0, round((c1 - e) / f::DOUBLE, 9) c1 FROM p, (SELECT min(c0) a, max(c0) - min(c0) b, min(c1) e, max(c1) - min(c1) f FROM p)"))(lambda s, d: fn.scaled(ps_of(s, d, "customer2d"), "minmax").df.select("point_id", F.round("c0", 9).alias("c0"), F.round("c1", 9).alias("c1")))
query("scale_zscore", Chain("customer2d").select("SELECT point_id, round((c0 - a) / b, 6) c0, round((c1 - e) / f, 6) c1 FROM p, (SELECT avg(c0) a, stddev_pop(c0) b, avg(c1) e, stddev_pop(c1) f FROM p)"))(lambda s, d: fn.scaled(ps_of(s, d, "customer2d"), "zscore").df.select("point_id", F.round("c0", 6).alias("c0"), F.round("c1", 6).alias("c1")))
query("filter_points", Chain("orders2d").select("SELECT * FROM p WHERE c1 BETWEEN 100 AND 400 AND c0 > 5000000"))(lambda s, d: fn.clean(ps_of(s, d, "orders2d").df, 2, "drop").filter("c1 between 100 and 400 and c0 > 5000000"))

# Trees and labels.


def tree(s, d, fixture, depth):
    return kdtree.build_exact(ps_of(s, d, fixture), depth)


def region_query(name, fixture, depth):
    query(name, Chain(fixture).tree(depth).select("SELECT point_id, region_id FROM regions"))(lambda s, d: tree(s, d, fixture, depth).select("point_id", "region_id"))


region_query("kd_region_exact", "orders2d", 6)
region_query("kd_region_ties", "lineitem2d", 5)
region_query("kd_axis_cycle", "embed8", 4)
region_query("edge_tree_small", "nation1d", 3)
region_query("edge_no_split", "region1d", 0)


query("kd_region_widest", Chain("customer2d").tree(5, widest=True).select("SELECT point_id, region_id FROM regions"))(lambda s, d: kdtree.build_exact(ps_of(s, d, "customer2d"), 5, "widest").select("point_id", "region_id"))
query("kd_planes_widest", ORACLES["kd_region_widest"])(lambda s, d: kdtree.assign_region(ps := ps_of(s, d, "customer2d"), kdtree.build_planes_exact(ps, 5, "widest"), 5).select("point_id", "region_id"))
#: A column whose values are all equal is never the widest; cut in turn it still gives regions of equal size, by ids.
_FLAT = "SELECT point_id, c0, 7::BIGINT c1 FROM p"


def flat(s, d) -> PointSet:
    return PointSet(ps_of(s, d, "customer2d").df.withColumn("c1", F.lit(7).cast("long")), 2)


query("edge_constant_column", Chain("customer2d").add("q", _FLAT).select("SELECT 1").replace("SELECT 1", "SELECT count(*) regions, max(n) - min(n) <= 1 even FROM (SELECT count(*) n FROM (SELECT CASE WHEN rn > (n + 1) // 2 THEN 1 ELSE 0 END r FROM (SELECT *, row_number() OVER (ORDER BY c0, point_id) rn, count(*) OVER () n FROM q)) GROUP BY r)"))(lambda s, d: kdtree.build_exact(flat(s, d), 1).groupBy("region_id").count().agg(F.count("*").alias("regions"), (F.max("count") - F.min("count") <= 1).alias("even")))
query("edge_duplicates", Chain("customer2d", "point_id < 200").add("two", "SELECT point_id * 2 point_id, c0, c1 FROM p UNION ALL SELECT point_id * 2 + 1, c0, c1 FROM p").select("SELECT count(*) points, count(DISTINCT (c0, c1)) places FROM two"))(lambda s, d: (lambda ps: labeling.by_axis(kdtree.build_exact(PointSet(ps.withColumn("point_id", F.explode(F.array(F.col("point_id") * 2, F.col("point_id") * 2 + 1))), 2), 3)).agg(F.count("*").alias("points"), F.count_distinct("c0", "c1").alias("places")))(ps_of(s, d, "customer2d").df.filter("point_id < 200")))


@query("edge_more_clusters_than_points", "SELECT count(*) regions, true refused FROM region")
def edge_more_clusters_than_points(s, d):
    """K over n is refused; what is asked for would have empty clusters only."""
    ps = ps_of(s, d, "region1d")
    try:
        kmeans.subset_kmeans(ps, 6, np.zeros((6, 1)), subsets=1, partition="random", labels="random")
        refused = False
    except ValueError:
        refused = True
    return ps.df.agg(F.count("*").alias("regions")).withColumn("refused", F.lit(refused))


@query("edge_as_many_clusters_as_points", "SELECT 0::BIGINT sse")
def edge_as_many_clusters_as_points(s, d):
    """K = n: every point is its own centroid."""
    ps = ps_of(s, d, "region1d")
    r = kmeans.subset_kmeans(ps, 5, kmeans.first_k(ps, 5), subsets=1, partition="random", labels="random")
    return kmeans.sse(ps, r.centroids)


@query("kd_planes_exact", Chain("lineitem2d").tree(4).select("SELECT point_id, region_id FROM regions"))
def kd_planes_exact(s, d):
    ps = ps_of(s, d, "lineitem2d")
    return kdtree.assign_region(ps, kdtree.build_planes_exact(ps, 4), 4).select("point_id", "region_id")


@query("kd_assign", Chain("gauss3k").tree(5).select("SELECT point_id, region_id FROM regions"))
def kd_assign(s, d):
    ps = ps_of(s, d, "gauss3k")
    return kdtree.assign_region(ps, kdtree.build_planes_exact(ps, 5, bins=64), 5).select("point_id", "region_id")


def balance(s, d, build):
    ps = ps_of(s, d, "orders2d")
    n = ps.count()
    sizes = kdtree.assign_region(ps, build(ps), 4).groupBy("region_id").count()
    return sizes.agg(F.count("*").alias("regions"), (F.max("count") * 16 / n).alias("largest_to_even"), (F.min("count") * 16 / n).alias("smallest_to_even"))


query("kd_planes_sketch")(lambda s, d: balance(s, d, lambda ps: kdtree.build_planes_sketch(ps, 4)))
query("kd_planes_sampled")(lambda s, d: balance(s, d, lambda ps: kdtree.build_planes_sampled(ps, 4, 64)))

#: The orders of each priority as a point set: how many have a price.
_SETS = "SELECT o_orderpriority points, count(o_totalprice) n FROM orders GROUP BY 1"


def sets(s, d) -> DataFrame:
    return fn.table(s, d, "orders").groupBy(F.col("o_orderpriority").alias("points")).agg(F.count("o_totalprice").alias("n"))


def each_of(df: DataFrame, names: Sequence[str], values: Sequence[tuple]) -> DataFrame:
    """Every row beside each of a few settings."""
    return df.crossJoin(F.broadcast(df.sparkSession.createDataFrame(list(values), ", ".join(f"{x} long" for x in names))))


def rule(f, kind: str, *args: str):
    """A rule of the method as a column."""
    return F.udf(f, kind)(*args)


_CAPACITIES = [(6,), (12,), (24,), (47,), (94,), (59,), (118,), (235,), (469,), (938,), (10**9,)]
_OF = lambda names, values: f"({_SETS}) a, (VALUES {', '.join('(' + ', '.join(map(str, v)) + ')' for v in values)}) v({', '.join(names)})"
query("kd_depth", f"SELECT points, n, capacity::BIGINT capacity, greatest(0, ceil(log2(n::DOUBLE / capacity)))::INT depth FROM {_OF(['capacity'], _CAPACITIES)}")(lambda s, d: each_of(sets(s, d), ["capacity"], _CAPACITIES).withColumn("depth", rule(kdtree.depth_for, "int", "n", "capacity")))
_RANGE = (Chain("orders2d").tree(4).select("SELECT DISTINCT region_id FROM regions WHERE c0 BETWEEN 10000000 AND 20000000 AND c1 BETWEEN 200 AND 500"))


@query("kd_range", _RANGE)
def kd_range(s, d):
    ps = ps_of(s, d, "orders2d")
    planes = kdtree.build_planes_exact(ps, 4)
    box = {0: (10_000_000, 20_000_000), 1: (200, 500)}
    some = kdtree.assign_region(ps, planes, 4).filter(F.col("region_id").isin(kdtree.range_regions(planes, 4, box)))
    return some.filter("c0 between 10000000 and 20000000 and c1 between 200 and 500").select("region_id").distinct()


def label_query(name, how, ragged="keep", m=None, fixture="orders2d", depth=5, tail="", seed=0):
    sql = Chain(fixture).tree(depth).labels(how, m, ragged, seed).select("SELECT point_id, region_id, label FROM lab" + (f" WHERE {tail}" if tail else ""))

    def run(s, d):
        deal = labeling.by_axis if how == "axis" else labeling.by_random
        kw = {"seed": seed} if how != "axis" else {}
        df = deal(tree(s, d, fixture, depth), subsets=m, ragged=ragged, **kw).select("point_id", "region_id", "label")
        return df.filter(tail) if tail else df

    query(name, sql)(run)


label_query("label_axis", "axis")
label_query("label_random", "random", seed=3)
label_query("label_ragged_keep", "axis", "keep", fixture="gauss3k", depth=7)
label_query("label_ragged_drop", "axis", "drop", 20, "gauss3k", 7)
label_query("label_ragged_prop", "axis", "proportional", 7, "gauss3k", 7)
label_query("subset_members", "axis", tail="label = 2")
query("partition_random", Chain("customer2d").dealt(7).select("SELECT point_id, label FROM lab"))(lambda s, d: labeling.random_partition(ps_of(s, d, "customer2d").df, 7).select("point_id", "label"))
query("prethin_members", Chain("orders2d").select("SELECT point_id FROM p, (SELECT count(*) n FROM p) WHERE ('0x' || substr(md5(concat('0:', point_id)), 1, 8))::BIGINT < least(4294967296, (200 * 4294967296 + n - 1) // n)"))(lambda s, d: labeling.prethin((p := ps_of(s, d, "orders2d")).df, p.count(), 200).select("point_id"))
query("coverage", Chain("gauss3k").tree(6).labels("axis").select("SELECT label, count(DISTINCT region_id) regions, count(*) points FROM lab GROUP BY 1"))(lambda s, d: measures.coverage(labeling.by_axis(tree(s, d, "gauss3k", 6))))
query("region_balance", Chain("gauss3k").tree(6).select("SELECT points, count(*) regions FROM (SELECT count(*) points FROM regions GROUP BY region_id) GROUP BY 1"))(lambda s, d: measures.region_balance(tree(s, d, "gauss3k", 6)))
query("subset_sizes", Chain("gauss3k").tree(6).labels("axis", 10, "proportional").select("SELECT label, count(*) points FROM lab GROUP BY 1"))(lambda s, d: measures.subset_sizes(labeling.by_axis(tree(s, d, "gauss3k", 6), subsets=10, ragged="proportional")))
query("fn_bit_path", Chain("orders2d").tree(3).select("SELECT point_id, substr(bin(region_id), 2) bit_path FROM regions"))(lambda s, d: tree(s, d, "orders2d", 3).select("point_id", kdtree.bit_path(F.col("region_id")).alias("bit_path")))

# Solving and merging.

R = "SELECT cluster_id, {c} FROM model"


def candidates(s, d, fixture, depth, m, init, t, ragged="proportional", labels="axis", partition="tree", seed=0, solver="plain", asse="sq", most=None):
    ps = ps_of(s, d, fixture)
    lab = kmeans.labelled(ps, depth, m, partition, labels, ragged=ragged, seed=seed)
    lab = lab.filter(F.col("label") <= most) if most else lab
    c0 = kmeans.of_ids(ps, init)
    return ps, subset.solve(lab, c0, ps.d, t, solver=solver, asse=asse)


def chain(fixture, depth, m, init, t, ragged="proportional", labels="axis", partition="tree", seed=0, most="true"):
    c = Chain(fixture)
    c = c.tree(depth).labels(labels, m, ragged, seed) if partition == "tree" else c.dealt(m, seed)
    return c.start(init).rounds(t, most)


_S1 = INITIAL[1]
_CAND = "SELECT subset_id, cluster_id::INT cluster_id, {c}, members, sse FROM cand"
query("subset_candidates", chain("orders2d", 6, None, (0, 1, 2), T_REAL, "keep").select(_CAND.format(c=cols(2))))(lambda s, d: candidates(s, d, "orders2d", 6, None, (0, 1, 2), T_REAL, "keep")[1].select("subset_id", "cluster_id", "c0", "c1", "members", "sse"))
for _solver in ("bounds", "kdfilter"):
    query(f"subset_candidates_{_solver}", chain("orders2d", 6, None, (0, 1, 2), T_REAL, "keep").select(_CAND.format(c=cols(2))))(lambda s, d, v=_solver: candidates(s, d, "orders2d", 6, None, (0, 1, 2), T_REAL, "keep", solver=v)[1].select("subset_id", "cluster_id", "c0", "c1", "members", "sse"))
query("asse_sq", chain("gauss3k", 6, 46, _S1, T_GAUSS).select("SELECT DISTINCT subset_id, asse FROM cand"))(lambda s, d: candidates(s, d, "gauss3k", 6, 46, _S1, T_GAUSS)[1].select("subset_id", "asse").distinct())
query("asse_dist", chain("gauss3k", 6, 46, _S1, T_GAUSS).select("SELECT DISTINCT subset_id, round(asse_dist, 3) asse FROM cand"))(lambda s, d: candidates(s, d, "gauss3k", 6, 46, _S1, T_GAUSS, asse="dist")[1].select("subset_id", F.round("asse", 3).alias("asse")).distinct())
query("rounds_per_subset", chain("gauss3k", 7, 23, _S1, T_GAUSS).settled(T_GAUSS).select("SELECT s subset_id, rounds::INT rounds, rounds IS NOT NULL converged FROM settled"))(lambda s, d: candidates(s, d, "gauss3k", 7, 23, _S1, 100)[1].select("subset_id", "rounds", "converged").distinct())


def model_query(name, fixture, depth, m, init, t=T_GAUSS, how="min_asse", by="asse", **kw):
    c = chain(fixture, depth, m, init, t, **kw)
    c = c.best(by) if how == "min_asse" else c.merged(len(init) * m, len(init))

    def run(s, d):
        ps, cands = candidates(s, d, fixture, depth, m, init, t, asse="sq" if by == "asse" else "dist", **kw)
        return rows(s, merge.min_asse(cands, ps.d) if how == "min_asse" else merge.hierarchical(cands, len(init), ps.d))

    query(name, c.select(R.format(c=cols(dims(fixture)))))(run)


def sse_query(name, fixture, depth, m, init, t=T_GAUSS, how="min_asse", where=None, **kw):
    c = chain(fixture, depth, m, init, t, **kw)
    c = (c.best() if how == "min_asse" else c.merged(len(init) * m, len(init))).scored()

    def run(s, d):
        ps, cands = candidates(s, d, fixture, depth, m, init, t, **kw)
        return kmeans.sse(ps, merge.min_asse(cands, ps.d) if how == "min_asse" else merge.hierarchical(cands, len(init), ps.d))

    query(name, c.select(SSE))(run)


model_query("merge_min_asse", "gauss3k", 6, 46, _S1)
model_query("merge_min_asse_dist", "gauss3k", 6, 46, _S1, by="asse_dist")
model_query("merge_hierarchical", "gauss3k", 9, 5, _S1, how="hierarchical")
_HIER = chain("gauss3k", 9, 5, _S1, T_GAUSS).merged(20, 4).select(R.format(c="c0, c1"))
query("merge_hierarchical_distributed", _HIER)(lambda s, d: rows(s, merge.hierarchical_distributed(candidates(s, d, "gauss3k", 9, 5, _S1, T_GAUSS)[1], 4, 2)))
query("merge_hierarchical_one_group", _HIER)(lambda s, d: rows(s, merge.hierarchical_grouped(candidates(s, d, "gauss3k", 9, 5, _S1, T_GAUSS)[1], 4, 2, weighted=False)))
query("merge_hierarchical_grouped")(lambda s, d: kmeans.sse(ps := ps_of(s, d, "gauss15k"), kmeans.subset_kmeans(ps, 4, kmeans.of_ids(ps, _S1), regions=64, how="grouped").centroids))
query("merge_hierarchical_weighted")(lambda s, d: kmeans.sse(ps := ps_of(s, d, "gauss3k"), merge.hierarchical(candidates(s, d, "gauss3k", 6, 46, _S1, T_GAUSS)[1], 4, 2, weighted=True)))
model_query("subset_kmeans_flagship", "orders2d", 6, 15, (0, 1, 2), T_REAL)
model_query("random_partition_kmeans", "gauss3k", 6, 46, _S1, partition="random", labels="random")
model_query("tree_random_kmeans", "gauss3k", 6, 46, _S1, labels="random")
model_query("tree_axis_hier_kmeans", "gauss3k", 9, 5, INITIAL[3], how="hierarchical")
query("subset_thinned", chain("gauss3k", 6, 46, _S1, T_GAUSS, most="label <= 8").best().select(R.format(c="c0, c1")))(lambda s, d: rows(s, merge.min_asse(candidates(s, d, "gauss3k", 6, 46, _S1, T_GAUSS, most=8)[1], 2)))
query("merge_closest_pair", chain("gauss3k", 9, 5, _S1, T_GAUSS).add("h", "SELECT (subset_id - 1) * 4 + cluster_id id, c0, c1 FROM cand").select("SELECT q.i, q.j, q.d dist2 FROM (SELECT min({'d': (a.c0 - b.c0) * (a.c0 - b.c0) + (a.c1 - b.c1) * (a.c1 - b.c1), 'i': a.id, 'j': b.id}) q FROM h a JOIN h b ON a.id < b.id)"))(lambda s, d: merge.closest_pair(candidates(s, d, "gauss3k", 9, 5, _S1, T_GAUSS)[1].select(((F.col("subset_id") - 1) * 4 + F.col("cluster_id")).alias("id"), "c0", "c1"), 2))

# One machine, and one job per round.


def plain(fixture, init, t):
    return Chain(fixture).whole().start(init).rounds(t).add("model", f"SELECT cluster_id, {cols(dims(fixture))} FROM cand")


_PLAIN = plain("gauss3k", _S1, T_GAUSS).select(R.format(c="c0, c1"))


def plain_query(name, run, fixture="gauss3k", init=_S1, t=T_GAUSS):
    def f(s, d):
        ps = ps_of(s, d, fixture)
        return rows(s, run(ps, kmeans.of_ids(ps, init), t).centroids)

    query(name, plain(fixture, init, t).select(R.format(c=cols(dims(fixture)))))(f)


plain_query("single_machine", lambda ps, c0, t: kmeans.single_machine(ps, 4, c0, t))
plain_query("one_subset_equals_plain", lambda ps, c0, t: kmeans.subset_kmeans(ps, 4, c0, subsets=1, partition="random", labels="random", max_iter=t))
plain_query("iter_kmeans_raw", lambda ps, c0, t: kmeans.iterative_kmeans(ps, 4, c0, combine=False, max_iter=t), init=INITIAL[5])
plain_query("iter_kmeans_combined", lambda ps, c0, t: kmeans.iterative_kmeans(ps, 4, c0, max_iter=t), init=INITIAL[5])
plain_query("iter_kmeans_join", lambda ps, c0, t: kmeans.iterative_kmeans(ps, 4, c0, how="join", max_iter=t), init=INITIAL[5])
plain_query("iter_kmeans_cells", lambda ps, c0, t: kmeans.iterative_kmeans(ps, 4, c0, how="cells", regions=kdtree.build_exact(ps, 5), max_iter=t), init=INITIAL[5])
plain_query("empty_cluster_keep", lambda ps, c0, t: kmeans.iterative_kmeans(ps, 3, c0, max_iter=t), "customer2d", (1, 1, 2), 4)

_TRACE = plain("gauss3k", INITIAL[5], T_GAUSS).select(" UNION ALL ".join(f"SELECT {r} round, sum(floor(b.d)::BIGINT)::BIGINT sse FROM a{r}" for r in range(1, 4)))


@query("convergence_trace", _TRACE)
def convergence_trace(s, d):
    ps = ps_of(s, d, "gauss3k")
    r = kmeans.iterative_kmeans(ps, 4, kmeans.of_ids(ps, INITIAL[5]), max_iter=3)
    return s.createDataFrame([(n, e) for n, e, _ in r.trace], "round int, sse long")


query("init_first_k", Chain("orders2d").select("SELECT (row_number() OVER (ORDER BY point_id) - 1)::INT cluster_id, c0::DOUBLE c0, c1::DOUBLE c1 FROM p QUALIFY row_number() OVER (ORDER BY point_id) <= 4"))(lambda s, d: rows(s, kmeans.first_k(ps_of(s, d, "orders2d"), 4)))
query("init_random_k", Chain("orders2d").select("SELECT (row_number() OVER (ORDER BY md5(concat('5:', point_id))) - 1)::INT cluster_id, c0::DOUBLE c0, c1::DOUBLE c1 FROM p QUALIFY row_number() OVER (ORDER BY md5(concat('5:', point_id))) <= 4"))(lambda s, d: rows(s, kmeans.random_k(ps_of(s, d, "orders2d"), 4, 5)))
query("random_sample_kmeans")(lambda s, d: rows(s, kmeans.random_sample_kmeans(p := ps_of(s, d, "gauss15k"), 4, kmeans.of_ids(p, _S1), 0.02, max_iter=30).centroids))
query("spark_ml_kmeans")(lambda s, d: kmeans.sse(p := ps_of(s, d, "gauss15k"), kmeans.spark_ml(p, 4).centroids))

# Assignment and measures of a fixed model.

_C = np.array([[0.0, 0.0], [9.0, 1.0], [2.0, 9.0], [10.0, 10.0]]) * fixtures.UNIT
_FIXED = Chain("gauss3k").add("model", " UNION ALL ".join(f"SELECT {k} cluster_id, {a!r}::DOUBLE c0, {b!r}::DOUBLE c1" for k, (a, b) in enumerate(_C.tolist()))).scored()
_ASSIGNED = _FIXED.select("SELECT point_id, b.k::INT cluster_id, b.d dist2 FROM scored")
for _name, _how in (("predict", assign.by_literal), ("assign_literal", assign.by_literal), ("assign_join", assign.by_join), ("assign_hof", assign.by_hof), ("assign_arrow", assign.by_arrow)):
    query(_name, _ASSIGNED)(lambda s, d, how=_how: how(ps_of(s, d, "gauss3k"), _C).select("point_id", "cluster_id", "dist2"))
query("assign_cells", _ASSIGNED)(lambda s, d: assign.by_cells(p := ps_of(s, d, "gauss3k"), kdtree.build_exact(p, 5), _C).select("point_id", "cluster_id", "dist2"))
query("sse", _FIXED.select(SSE))(lambda s, d: kmeans.sse(ps_of(s, d, "gauss3k"), _C))
query("cluster_profile", _FIXED.select("SELECT b.k::INT cluster_id, count(*) points, sum(floor(b.d)::BIGINT)::BIGINT sse FROM scored GROUP BY 1"))(lambda s, d: measures.cluster_profile(assign.by_literal(ps_of(s, d, "gauss3k"), _C)))
query("purity", _FIXED.select("SELECT sum(m) / sum(n) purity FROM (SELECT k, max(n) m, sum(n) n FROM (SELECT b.k k, truth, count(*) n FROM scored JOIN p USING (point_id) GROUP BY 1, 2) GROUP BY 1)"))(lambda s, d: measures.purity(assign.by_literal(ps_of(s, d, "gauss3k"), _C)))
query("centroid_update", _FIXED.select("SELECT b.k::INT cluster_id, count(*) n, sum(c0)::BIGINT s_c0, sum(c1)::BIGINT s_c1 FROM scored GROUP BY 1"))(lambda s, d: assign.sums(assign.by_literal(ps_of(s, d, "gauss3k"), _C), ["c0", "c1"]))
query("topk_per_cluster", _FIXED.select("SELECT b.k::INT cluster_id, point_id FROM scored QUALIFY row_number() OVER (PARTITION BY b.k ORDER BY b.d, point_id) <= 3"))(lambda s, d: assign.by_literal(ps_of(s, d, "gauss3k"), _C).withColumn("r", F.row_number().over(Window.partitionBy("cluster_id").orderBy("dist2", "point_id"))).filter("r <= 3").select("cluster_id", "point_id"))


def ratio_chain(fixture, depth, m, init):
    c = chain(fixture, depth, m, init, T_GAUSS).best().scored()
    one = plain(fixture, init, T_GAUSS).scored()
    return f"SELECT round(a.sse::DOUBLE / b.sse, 9) sse_ratio FROM ({c.select(SSE)}) a, ({one.select(SSE)}) b"


@query("sse_ratio", ratio_chain("gauss3k", 6, 46, _S1))
def sse_ratio(s, d):
    ps, cands = candidates(s, d, "gauss3k", 6, 46, _S1, T_GAUSS)
    a = kmeans.sse(ps, merge.min_asse(cands, 2)).first()[0]
    b = kmeans.sse(ps, kmeans.single_machine(ps, 4, kmeans.of_ids(ps, _S1), T_GAUSS).centroids).first()[0]
    return s.createDataFrame([(round(a / b, 9),)], "sse_ratio double")


#: The option grid: five subset counts, errors averaged over the seeds of random labels.
GRID_DEPTHS, GRID_SEEDS = (9, 8, 7, 6, 5), (0, 1, 2)


@query("grid_sse")
def grid_sse(s, d):
    ps = ps_of(s, d, "gauss3k")
    ps = PointSet(ps.df.persist(), ps.d)
    runs = [kmeans.grid(ps, 4, kmeans.of_ids(ps, _S1), GRID_DEPTHS, ps.count(), seed) for seed in GRID_SEEDS]
    mean = [(*same[0][:4], round(sum(r[4] for r in same) / len(same))) for same in zip(*runs, strict=True)]
    ps.df.unpersist()
    return s.createDataFrame(mean, "partition string, labels string, how string, subsets int, sse long")


query("grid_rank")(lambda s, d: measures.rank_combinations(grid_sse(s, d)))
query("partition_check", "SELECT 0::BIGINT lost, 0::BIGINT invented, 0::BIGINT doubled")(lambda s, d: measures.partition_check(ps_of(s, d, "orders2d").df, labeling.by_axis(tree(s, d, "orders2d", 5))))

# Closed forms of cost.

_RUNS = [(6, 18), (12, 18), (59, 19), (938, 19)]
_DEPTH = "greatest(0, ceil(log2(n::DOUBLE / capacity)))::BIGINT"
#: K, and log2 of the regions, of which there is one point in a subset.
_MERGES = [(4, 9), (4, 5), (8, 7)]
query("cost_model_jobs", f"SELECT points, n, capacity::BIGINT capacity, {_DEPTH} + 2 method_jobs, rounds::BIGINT baseline_jobs FROM {_OF(['capacity', 'rounds'], _RUNS)}")(lambda s, d: each_of(sets(s, d), ["capacity", "rounds"], _RUNS).withColumn("j", rule(measures.model_jobs, "struct<method: long, baseline: long>", "n", "capacity", "rounds")).select("points", "n", "capacity", F.col("j.method").alias("method_jobs"), F.col("j.baseline").alias("baseline_jobs")))


def subsets_of(s, d) -> DataFrame:
    return each_of(sets(s, d), ["k", "depth"], _MERGES).withColumn("m", F.expr("n div shiftleft(1L, cast(depth as int))"))


_SUBSETS = f"(SELECT points, k::BIGINT k, n // (1::BIGINT << depth) m FROM {_OF(['k', 'depth'], _MERGES)})"
query("cost_model_merge", f"SELECT points, k, m, (k * m) * (k * m) * (k * m) hierarchical, k * m min_asse FROM {_SUBSETS}")(lambda s, d: subsets_of(s, d).withColumn("c", rule(measures.model_merge, "struct<hierarchical: long, min_asse: long>", "k", "m")).select("points", "k", "m", "c.hierarchical", "c.min_asse"))
query("cost_model_width", f"SELECT points, k, m, k baseline_width, m method_width FROM {_SUBSETS}")(lambda s, d: subsets_of(s, d).select("points", "k", "m", F.col("k").alias("baseline_width"), F.col("m").alias("method_width")))
_VOLUMES = [(9, 18, 4, 8), (8, 19, 4, 8)]
query("cost_model_volume", f"SELECT points, n, n * (depth + 2) method_exact, 2 * n method_planes, n * rounds baseline_raw, (k * parts * rounds)::BIGINT baseline_combined FROM {_OF(['depth', 'rounds', 'k', 'parts'], _VOLUMES)}")(lambda s, d: each_of(sets(s, d), ["depth", "rounds", "k", "parts"], _VOLUMES).withColumn("v", rule(lambda *x: tuple(measures.model_volume(*x).values()), "struct<a: long, b: long, c: long, d: long>", "n", "depth", "rounds", "k", "parts")).select("points", "n", F.col("v.a").alias("method_exact"), F.col("v.b").alias("method_planes"), F.col("v.c").alias("baseline_raw"), F.col("v.d").alias("baseline_combined")))

# Experiment workloads.

for _i in INITIAL:
    sse_query(f"w1_sse_init{_i}", "gauss3k", 9, 5, INITIAL[_i])
for _depth, _m in ((8, 11), (7, 23), (6, 46), (5, 93)):
    sse_query(f"w2_sse_{_m}_subsets", "gauss3k", _depth, _m, _S1)
for _depth, _m in ((8, 58), (7, 117), (6, 234), (5, 468), (4, 937)):
    sse_query(f"w4_sse_{_m}_subsets", "gauss15k", _depth, _m, _S1)
# The baseline's error from each start, the setting of six subsets (five of one point per region and one of the rest), and one machine.
for _i in INITIAL:
    query(f"w1_baseline_init{_i}", plain("gauss3k", INITIAL[_i], T_GAUSS).scored().select(SSE))(lambda s, d, i=_i: kmeans.sse(ps := ps_of(s, d, "gauss3k"), kmeans.iterative_kmeans(ps, 4, kmeans.of_ids(ps, INITIAL[i]), max_iter=T_GAUSS).centroids))
sse_query("w2_sse_6_subsets", "gauss3k", 9, None, _S1, ragged="keep")
for _name, _run in (("w4_single_machine", kmeans.single_machine), ("w4_baseline", kmeans.iterative_kmeans)):
    query(_name, plain("gauss15k", _S1, T_GAUSS).scored().select(SSE))(lambda s, d, run=_run: kmeans.sse(ps := ps_of(s, d, "gauss15k"), run(ps, 4, kmeans.of_ids(ps, _S1), max_iter=T_GAUSS).centroids))
# The option grid: random labels with and without a tree at all five subset counts, and hierarchical merging where SQL can unroll it.
for _depth, _m in ((9, 5), (8, 11), (7, 23), (6, 46), (5, 93)):
    sse_query(f"w3_random_labels_{_m}", "gauss3k", _depth, _m, _S1, labels="random", seed=1)
    sse_query(f"w3_no_tree_{_m}", "gauss3k", _depth, _m, _S1, partition="random", labels="random", seed=1)
sse_query("w3_random_labels_hierarchical", "gauss3k", 9, 5, _S1, how="hierarchical", labels="random", seed=1)
sse_query("w3_no_tree_hierarchical", "gauss3k", 9, 5, _S1, how="hierarchical", partition="random", labels="random", seed=1)
sse_query("w3_random_labels", "gauss3k", 6, 46, _S1, labels="random", seed=1)
sse_query("w3_no_tree", "gauss3k", 6, 46, _S1, partition="random", labels="random", seed=1)
sse_query("w3_hierarchical", "gauss3k", 9, 5, _S1, how="hierarchical")
for _name, _f, _depth, _m, _init in (("w9_lineitem", "lineitem2d", 8, 20, (1, 2, 3)), ("w10_orders", "orders2d", 6, 20, (0, 1, 2)), ("w11_events", "events2d", 6, 15, (0, 1, 2)), ("w12_embed8", "embed8", 4, 20, (0, 1, 2)), ("w13_customer", "customer2d", 5, 10, (0, 1, 2)), ("w13_part", "part2d", 5, 10, (0, 1, 2)), ("w13_supplier", "supplier1d", 2, 4, (0, 1)), ("w14_documents", "docs2d", 4, 12, (0, 1, 2))):
    model_query(_name, _f, _depth, _m, _init, T_REAL)


@query("w5_figure_rows", chain("gauss3k", 8, 11, _S1, T_GAUSS).best().select("SELECT 'centroid' kind, cluster_id::BIGINT id, c0, c1 FROM model UNION ALL SELECT 'initial', k, x0, x1 FROM init UNION ALL SELECT 'subset 2', point_id, c0::DOUBLE, c1::DOUBLE FROM lab WHERE label = 2"))
def w5_figure_rows(s, d):
    ps = ps_of(s, d, "gauss3k")
    r = kmeans.subset_kmeans(ps, 4, c0 := kmeans.of_ids(ps, _S1), subsets=11, max_iter=T_GAUSS)
    part = lambda kind, df, i: df.select(F.lit(kind).alias("kind"), F.col(i).cast("long").alias("id"), F.col("c0").cast("double").alias("c0"), F.col("c1").cast("double").alias("c1"))
    return part("centroid", rows(s, r.centroids), "cluster_id").union(part("initial", rows(s, c0), "cluster_id")).union(part("subset 2", labeling.subset(r.labelled, 2), "point_id"))


_EASY = Chain("gauss3k").whole().start(rows=_C.tolist()).rounds(10).settled(10).select("SELECT rounds::INT rounds, (SELECT sum(floor(b.d)::BIGINT)::BIGINT FROM a10) sse FROM settled")


@query("w7_rounds", _EASY)
def w7_rounds(s, d):
    """An easy start: the baseline ends after a few rounds."""
    ps = ps_of(s, d, "gauss3k")
    r = kmeans.iterative_kmeans(ps, 4, _C)
    return s.createDataFrame([(r.rounds, r.trace[-1][1])], "rounds int, sse long")


#: Where the points of a cost run lie: read anew by every job, as the compared implementations do.
COST_COLUMNS = "run string, experiment int, rounds int, jobs int, exchanges int, tasks int, ms int, bytes_moved long, bytes_shuffled long, rows_shuffled long, sse long"


def cost_rows(s, ps: PointSet, experiment: int, init, depth: int) -> list[tuple]:
    """One row for the method, and one each for the baseline with and without sums before the shuffle."""
    out = []
    n = ps.count()
    runs = (
        ("method", lambda: kmeans.subset_kmeans(ps, 4, init, regions=1 << depth, n=n, max_iter=100)),
        ("baseline", lambda: kmeans.iterative_kmeans(ps, 4, init, combine=False)),
        ("baseline, combined", lambda: kmeans.iterative_kmeans(ps, 4, init)),
    )
    for name, run in runs:
        with measures.Costs(s) as c:
            r = run()
        out.append((name, experiment, r.rounds, c.jobs, c.exchanges, c.tasks, c.ms, c.moved, c.shuffle_write, c.shuffle_rows, int(kmeans.sse(ps, r.centroids).first()[0])))
        r.release()
    return out


@query("w1_costs")
def w1_costs(s, d):
    """Five starts: jobs, time, bytes and error of the method and the baselines."""
    ps = ps_of(s, d, "gauss3k")
    return s.createDataFrame([row for i in INITIAL for row in cost_rows(s, ps, i, kmeans.of_ids(ps, INITIAL[i]), 9)], COST_COLUMNS)


@query("w1_cost_ratios")
def w1_cost_ratios(s, d):
    """The method's share of the baseline's jobs, time, bytes and error, by experiment."""
    c = w1_costs(s, d)
    a, b = c.filter("run = 'method'"), c.filter("run = 'baseline'")
    share = lambda x: F.round(F.col(f"a.{x}") / F.col(f"b.{x}"), 4).alias(f"{x}_ratio")
    return a.alias("a").join(b.alias("b"), "experiment").select("experiment", F.col("b.rounds").alias("baseline_rounds"), *map(share, ("jobs", "ms", "bytes_moved", "rows_shuffled", "sse")))


@query("w2_costs")
def w2_costs(s, d):
    """Growing subset counts: time, bytes and error of each."""
    ps, out = ps_of(s, d, "gauss3k"), []
    init, n = kmeans.of_ids(ps, _S1), ps.count()
    for depth in GRID_DEPTHS:
        with measures.Costs(s) as c:
            r = kmeans.subset_kmeans(ps, 4, init, regions=1 << depth, n=n)
        out.append((n >> depth, c.jobs, c.ms, c.run_ms, c.start_ms, c.wait_ms, c.moved, c.shuffle_rows, int(kmeans.sse(ps, r.centroids).first()[0])))
        r.release()
    return s.createDataFrame(out, "subsets int, jobs int, ms int, run_ms int, start_ms int, wait_ms int, bytes_moved long, rows_shuffled long, sse long")


@query("cost_counted_jobs")
def cost_counted_jobs(s, d):
    """Exchanges of points counted in a run, next to the closed form: of the tree, the labels and the subsets."""
    ps = ps_of(s, d, "gauss3k")
    init, n, out = kmeans.of_ids(ps, _S1), ps.count(), []
    for depth in (9, 7, 5):
        with measures.Costs(s) as c:
            r = kmeans.subset_kmeans(ps, 4, init, regions=1 << depth, tree="exact", n=n)
        r.release()
        out.append((depth, depth + 2, c.exchanges, c.shuffle_rows, n * (depth + 2)))
    return s.createDataFrame(out, "depth int, modelled int, counted int, rows_shuffled long, rows_modelled long")


@query("w6_shuffle_growth")
def w6_shuffle_growth(s, d):
    """Rows, bytes and milliseconds to deal out one, ten and a hundred copies of a table's points by key."""
    points, out = ps_of(s, d, "events2d").df, []
    for times in (1, 10, 100):
        grown = points.withColumn("copy", F.explode(F.sequence(F.lit(1), F.lit(times))))
        with measures.Costs(s) as c:
            got = grown.repartition(8, "point_id").groupBy(F.spark_partition_id()).count().agg(F.sum("count")).first()[0]
        out.append((int(got), c.shuffle_write, c.ms))
    return s.createDataFrame(out, "rows long, bytes_shuffled long, ms int")


@query("tradeoff")
def tradeoff(s, d):
    """Time and error of more subsets, against the fewest."""
    import time

    ps, runs = ps_of(s, d, "gauss3k"), []
    c0, n = kmeans.of_ids(ps, _S1), ps.count()
    for depth in (9, 7, 5):
        t = time.perf_counter()
        r = kmeans.subset_kmeans(ps, 4, c0, regions=1 << depth, n=n)
        runs.append((n >> depth, int(1000 * (time.perf_counter() - t)), int(kmeans.sse(ps, r.centroids).first()[0])))
    return measures.tradeoff(s.createDataFrame(runs, "subsets int, ms long, sse long"))


@query("centroid_match")
def centroid_match(s, d):
    """How far the method's centroids lie from one machine's, best pairing."""
    ps = ps_of(s, d, "gauss3k")
    c0 = kmeans.of_ids(ps, _S1)
    _, far = measures.centroid_match(kmeans.subset_kmeans(ps, 4, c0, regions=128).centroids, kmeans.single_machine(ps, 4, c0).centroids)
    return s.createDataFrame([(far,)], "largest_shift double")


@query("subset_kmeans_planes", ORACLES["subset_kmeans_flagship"])
def subset_kmeans_planes(s, d):
    """The flagship with cuts from histograms, which moves no point to build the tree."""
    ps = ps_of(s, d, "orders2d")
    cands = subset.solve(kmeans.labelled(ps, 6, 15, ragged="proportional", tree="planes"), kmeans.of_ids(ps, (0, 1, 2)), 2, T_REAL)
    return rows(s, merge.min_asse(cands, 2))


@query("subset_kmeans_rescored")
def subset_kmeans_rescored(s, d):
    """The best three subsets by their own error, judged again on all points."""
    ps = ps_of(s, d, "gauss3k")
    return kmeans.sse(ps, kmeans.subset_kmeans(ps, 4, kmeans.of_ids(ps, _S1), regions=64, rescore=3).centroids)


@query("subset_kmeans_prethinned")
def subset_kmeans_prethinned(s, d):
    """A hash sample first, stratified by its own tree: nothing but the sample is shuffled."""
    ps = ps_of(s, d, "gauss15k")
    n = ps.count()
    thin = PointSet(labeling.prethin(ps.df, n, 2048, 1), 2)
    return kmeans.sse(ps, kmeans.subset_kmeans(thin, 4, kmeans.of_ids(ps, _S1), regions=128).centroids)


# The same operators over all events, without a statement: the forms above hold to the 3,000 points of the experiments.

_ALL = "gauss_events"


def whole_query(name, run):
    query(f"{name}_all")(lambda s, d: run(s, ps_of(s, d, _ALL)))


def _merged_all(**kw):
    return lambda s, ps: rows(s, kmeans.subset_kmeans(ps, 4, kmeans.of_ids(ps, _S1), regions=256, **kw).centroids)


for _name, _how in (("predict", assign.by_literal), ("assign_literal", assign.by_literal), ("assign_join", assign.by_join), ("assign_hof", assign.by_hof), ("assign_arrow", assign.by_arrow)):
    whole_query(_name, lambda s, ps, how=_how: how(ps, _C).select("point_id", "cluster_id", "dist2"))
whole_query("assign_cells", lambda s, ps: assign.by_cells(ps, kdtree.build_exact(ps, 5), _C).select("point_id", "cluster_id", "dist2"))
whole_query("sse", lambda s, ps: kmeans.sse(ps, _C))
whole_query("cluster_profile", lambda s, ps: measures.cluster_profile(assign.by_literal(ps, _C)))
whole_query("purity", lambda s, ps: measures.purity(assign.by_literal(ps, _C)))
whole_query("centroid_update", lambda s, ps: assign.sums(assign.by_literal(ps, _C), ["c0", "c1"]))
whole_query("topk_per_cluster", lambda s, ps: assign.by_literal(ps, _C).withColumn("r", F.row_number().over(Window.partitionBy("cluster_id").orderBy("dist2", "point_id"))).filter("r <= 3").select("cluster_id", "point_id"))
whole_query("coverage", lambda s, ps: measures.coverage(labeling.by_axis(kdtree.build_exact(ps, 6))))
whole_query("region_balance", lambda s, ps: measures.region_balance(kdtree.build_exact(ps, 6)))
whole_query("subset_sizes", lambda s, ps: measures.subset_sizes(labeling.by_axis(kdtree.build_exact(ps, 6), subsets=10, ragged="proportional")))
whole_query("kd_assign", lambda s, ps: kdtree.assign_region(ps, kdtree.build_planes_exact(ps, 5, bins=64), 5).select("point_id", "region_id"))
whole_query("merge_min_asse", _merged_all())
whole_query("merge_min_asse_dist", _merged_all(asse="dist"))
whole_query("merge_hierarchical", lambda s, ps: rows(s, kmeans.subset_kmeans(ps, 4, kmeans.of_ids(ps, _S1), subsets=5, how="hierarchical").centroids))
whole_query("single_machine", lambda s, ps: rows(s, kmeans.single_machine(ps, 4, kmeans.of_ids(ps, _S1)).centroids))
for _name, _kw in (("raw", {"combine": False}), ("combined", {}), ("join", {"how": "join"})):
    whole_query(f"iter_kmeans_{_name}", lambda s, ps, kw=_kw: rows(s, kmeans.iterative_kmeans(ps, 4, kmeans.of_ids(ps, INITIAL[5]), **kw).centroids))
whole_query("iter_kmeans_cells", lambda s, ps: rows(s, kmeans.iterative_kmeans(ps, 4, kmeans.of_ids(ps, INITIAL[5]), how="cells", regions=kdtree.build_exact(ps, 5)).centroids))


# Real tables refined to convergence, without a statement: the forms above stop after T_REAL rounds, which is what SQL can unroll.


def converged(s, d, fixture, depth, m, init, ragged="proportional", **kw):
    """Points and candidates, once every subset has converged. A subset that has not stops the query."""
    ps, c0 = ps_of(s, d, fixture), kmeans.of_ids(ps_of(s, d, fixture), init)
    cands = subset.solve(kmeans.labelled(ps, depth, m, ragged=ragged, **{k: v for k, v in kw.items() if k == "tree"}), c0, ps.d, None, solver=kw.get("solver", "plain"))
    late = F.when(F.col("converged"), F.col("subset_id")).otherwise(F.raise_error(F.lit("a subset did not converge")))
    return ps, cands.withColumn("subset_id", late)


def converged_model(name, *at, **kw):
    def run(s, d):
        ps, cands = converged(s, d, *at, **kw)
        return rows(s, merge.min_asse(cands, ps.d))

    query(f"{name}_converged")(run)


for _solver in ("plain", "bounds", "kdfilter"):
    query("subset_candidates_converged" if _solver == "plain" else f"subset_candidates_{_solver}_converged")(lambda s, d, v=_solver: converged(s, d, "orders2d", 6, None, (0, 1, 2), "keep", solver=v)[1].select("subset_id", "cluster_id", "c0", "c1", "members", "sse", "rounds", "converged"))
converged_model("subset_kmeans_flagship", "orders2d", 6, 15, (0, 1, 2))
converged_model("subset_kmeans_planes", "orders2d", 6, 15, (0, 1, 2), tree="planes")
for _name, *_at in (("w9_lineitem", "lineitem2d", 8, 20, (1, 2, 3)), ("w10_orders", "orders2d", 6, 20, (0, 1, 2)), ("w11_events", "events2d", 6, 15, (0, 1, 2)), ("w12_embed8", "embed8", 4, 20, (0, 1, 2)), ("w13_customer", "customer2d", 5, 10, (0, 1, 2)), ("w13_part", "part2d", 5, 10, (0, 1, 2)), ("w13_supplier", "supplier1d", 2, 4, (0, 1)), ("w14_documents", "docs2d", 4, 12, (0, 1, 2))):
    converged_model(_name, *_at)

# Clusters of documents next to their labels, and of the other texts by their lengths.
_D14 = np.array([[500.0, 80.0], [3000.0, 500.0], [12_000.0, 2000.0]])
_W14 = Chain("docs2d").add("model", " UNION ALL ".join(f"SELECT {k} cluster_id, {a!r}::DOUBLE c0, {b!r}::DOUBLE c1" for k, (a, b) in enumerate(_D14.tolist()))).scored().select("SELECT b.k::INT cluster_id, count(*) points, count(quality) labelled, count(*) FILTER (quality = 1) good, count(*) FILTER (toxic = 1) toxic FROM scored LEFT JOIN labels ON doc_id = point_id GROUP BY 1")
query("w14_labels", _W14)(lambda s, d: assign.by_literal(ps_of(s, d, "docs2d"), _D14).join(fn.table(s, d, "labels"), F.col("doc_id") == F.col("point_id"), "left").groupBy("cluster_id").agg(F.count("*").alias("points"), F.count("quality").alias("labelled"), F.count_if(F.col("quality") == 1).alias("good"), F.count_if(F.col("toxic") == 1).alias("toxic")))
_LENGTHS = " UNION ALL ".join(f"SELECT '{t}' source, {i}::BIGINT id, length({c})::BIGINT c0, len(string_split({c}, ' '))::BIGINT c1 FROM {t}" for t, i, c in (("pages", "page_id", "html"), ("benchmark", "item_id", "text")))
query("w14_lengths", f"SELECT source, count(*) points, sum(c0)::BIGINT chars, max(c1) most_words FROM ({_LENGTHS}) GROUP BY 1")(lambda s, d: fn.lengths(s, d).groupBy("source").agg(F.count("*").alias("points"), F.sum("c0").alias("chars"), F.max("c1").alias("most_words")))


@query("w14_texts_converged")
def w14_texts_converged(s, d):
    """Pages and conversations by length, each clustered by the method."""
    out = []
    for name in ("pages2d", "turns2d"):
        ps = ps_of(s, d, name)
        c = kmeans.subset_kmeans(ps, 3, kmeans.first_k(ps, 3), regions=16).centroids
        out += [(name, k, *map(float, r)) for k, r in enumerate(c)]
    return s.createDataFrame(out, "points string, cluster_id int, c0 double, c1 double")


# Whole embeddings; the forms on embed8 are what SQL can follow. A tree of 4 levels cuts 4 axes, of 6 levels 6: distances take all 64.
query("featurize_embed64")(lambda s, d: ps_of(s, d, "embed64").df)
query("kd_axis_cycle_64")(lambda s, d: tree(s, d, "embed64", 6).select("point_id", "region_id"))
converged_model("w12_embed64", "embed64", 4, 20, (0, 1, 2))
