"""The relational operators that surround the method, each with its DuckDB statement."""

import uuid

import numpy as np
import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F

from strata.functions.points import PointSet, table
from strata.operators import assign
from strata.plans import kmeans
from strata.plans import queries as core
from strata.plans.queries import ps_of, query
from strata.sources import files
from strata.streaming import events as ev

c = F.col

# Joins.

query("join_broadcast", "SELECT n_nationkey, n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey")(lambda s, d: table(s, d, "nation").join(F.broadcast(table(s, d, "region")), c("n_regionkey") == c("r_regionkey")).select("n_nationkey", "n_name", "r_name"))
query("join_smj", "SELECT o_orderkey, c_mktsegment FROM orders JOIN customer ON o_custkey = c_custkey")(lambda s, d: table(s, d, "orders").hint("merge").join(table(s, d, "customer"), c("o_custkey") == c("c_custkey")).select("o_orderkey", "c_mktsegment"))
query("join_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 200000)")(lambda s, d: table(s, d, "customer").join(table(s, d, "orders").filter("o_totalprice > 200000"), c("o_custkey") == c("c_custkey"), "left_semi").select("c_custkey"))
query("join_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")(lambda s, d: table(s, d, "customer").join(table(s, d, "orders"), c("o_custkey") == c("c_custkey"), "left_anti").select("c_custkey"))
query("join_outer", "SELECT c_custkey, count(o_orderkey) n FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY 1")(lambda s, d: table(s, d, "customer").join(table(s, d, "orders"), c("o_custkey") == c("c_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n")))


@query("join_range", "SELECT p_partkey, (p_size - 1) // 10 AS cell FROM part WHERE p_retailprice < 1200")
def join_range(s, d):
    """Value to 1-D cell: an equi-join on a bin, then the bounds."""
    cells = s.range(5).select(c("id").cast("int").alias("cell"), (c("id") * 10).alias("lo"), (c("id") * 10 + 10).alias("hi"), c("id").alias("bin"))
    p = table(s, d, "part").filter("p_retailprice < 1200").withColumn("bin", F.floor((c("p_size") - 1) / 10))
    return p.join(F.broadcast(cells), "bin").filter("p_size > lo and p_size <= hi").select("p_partkey", "cell")


@query("join_asof", "WITH v AS (SELECT user_id, event_id vid, ts vts FROM events WHERE event_id % 10 = 0) SELECT e.event_id, max(v.vid) FILTER (v.vts <= e.ts) model_id FROM events e LEFT JOIN v ON v.user_id = e.user_id AND v.vts <= e.ts GROUP BY 1")
def join_asof(s, d):
    """The last model version at each event: one window over both, no pairs."""
    e = table(s, d, "events")
    both = e.select("user_id", "ts", "event_id", F.lit(1).alias("kind"), F.lit(None).cast("long").alias("v")).union(e.filter("event_id % 10 = 0").select("user_id", "ts", c("event_id"), F.lit(0), c("event_id")))
    w = Window.partitionBy("user_id").orderBy("ts", "kind", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("model_id", F.last("v", ignorenulls=True).over(w)).filter("kind = 1").select("event_id", "model_id")


@query("join_interval", "SELECT a.event_id, count(*) n FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts < a.ts + INTERVAL 6 HOUR GROUP BY 1")
def join_interval(s, d):
    e = table(s, d, "events").select("user_id", "event_id", (F.unix_micros(c("ts").cast("timestamp")) / 1e6).cast("double").alias("t"))
    b = e.select("user_id", c("t").alias("t2"))
    return e.join(b, "user_id").filter("t2 >= t and t2 < t + 21600").groupBy("event_id").agg(F.count("*").alias("n"))


# Aggregates.

_G = "FROM orders GROUP BY {g}"
query("agg_rollup", "SELECT o_orderstatus, o_orderpriority, count(*) n FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)")(lambda s, d: table(s, d, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n")))
query("agg_cube", "SELECT o_orderstatus, o_orderpriority, grouping_id(o_orderstatus, o_orderpriority)::INT g, count(*) n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")(lambda s, d: table(s, d, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.grouping_id().cast("int").alias("g"), F.count("*").alias("n")))
query("agg_grouping_sets", "SELECT o_orderstatus, o_orderpriority, count(*) n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority))")(lambda s, d: table(s, d, "orders").groupingSets([[c("o_orderstatus")], [c("o_orderpriority")]], "o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n")))
query("agg_pivot", "SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') f, count(*) FILTER (o_orderstatus = 'O') o FROM orders GROUP BY 1")(lambda s, d: table(s, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O"]).agg(F.count("o_orderkey")).select("o_orderpriority", F.coalesce("F", F.lit(0)).alias("f"), F.coalesce("O", F.lit(0)).alias("o")))
query("agg_distinct", "SELECT o_orderstatus, count(DISTINCT o_custkey) n FROM orders GROUP BY 1")(lambda s, d: table(s, d, "orders").groupBy("o_orderstatus").agg(F.count_distinct("o_custkey").alias("n")))
query("agg_approx_distinct")(lambda s, d: table(s, d, "orders").groupBy("o_orderstatus").agg(F.approx_count_distinct("o_custkey").alias("n")))
query("agg_min_by", "SELECT c_mktsegment, min(c_acctbal) least FROM customer GROUP BY 1")(lambda s, d: table(s, d, "customer").groupBy("c_mktsegment").agg(F.min_by("c_acctbal", F.struct("c_acctbal", "c_custkey")).alias("least")))
query("median_exact", "SELECT c_mktsegment, round(quantile_cont(c_acctbal, 0.5), 6) median FROM customer GROUP BY 1")(lambda s, d: table(s, d, "customer").groupBy("c_mktsegment").agg(F.round(F.percentile("c_acctbal", 0.5), 6).alias("median")))
query("median_sketch")(lambda s, d: table(s, d, "customer").groupBy("c_mktsegment").agg(F.percentile_approx("c_acctbal", 0.5, 10_000).alias("median")))
query("cluster_moments", "SELECT c_mktsegment, round(avg(c_acctbal), 4) mean, round(var_pop(c_acctbal), 2) var, round(corr(c_acctbal, c_nationkey), 6) r FROM customer GROUP BY 1")(lambda s, d: table(s, d, "customer").groupBy("c_mktsegment").agg(F.round(F.avg("c_acctbal"), 4).alias("mean"), F.round(F.var_pop("c_acctbal"), 2).alias("var"), F.round(F.corr("c_acctbal", "c_nationkey"), 6).alias("r")))

# Windows and sorting.


@query("win_rank_family", "SELECT c_custkey, row_number() OVER w rn, rank() OVER n rk, dense_rank() OVER n dr, ntile(2) OVER w half, round(percent_rank() OVER w, 9) pr FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey), n AS (PARTITION BY c_mktsegment ORDER BY c_nationkey)")
def win_rank_family(s, d):
    w = Window.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey")
    n = Window.partitionBy("c_mktsegment").orderBy("c_nationkey")
    return table(s, d, "customer").select("c_custkey", F.row_number().over(w).alias("rn"), F.rank().over(n).alias("rk"), F.dense_rank().over(n).alias("dr"), F.ntile(2).over(w).alias("half"), F.round(F.percent_rank().over(w), 9).alias("pr"))


@query("win_lag", "SELECT o_orderkey, round(o_totalprice - lag(o_totalprice) OVER w, 4) change, round(lead(o_totalprice) OVER w, 4) following FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def win_lag(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return table(s, d, "orders").select("o_orderkey", F.round(c("o_totalprice") - F.lag("o_totalprice").over(w), 4).alias("change"), F.round(F.lead("o_totalprice").over(w), 4).alias("following"))


@query("win_running", "SELECT o_orderkey, count(*) OVER w n, round(avg(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) moving FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING)")
def win_running(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return table(s, d, "orders").select("o_orderkey", F.count("*").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("n"), F.round(F.avg("o_totalprice").over(w.rowsBetween(-2, 0)), 4).alias("moving"))


query("win_range", "SELECT p_partkey, count(*) OVER (PARTITION BY p_brand ORDER BY p_size RANGE BETWEEN 5 PRECEDING AND 5 FOLLOWING) n FROM part")(lambda s, d: table(s, d, "part").select("p_partkey", F.count("*").over(Window.partitionBy("p_brand").orderBy("p_size").rangeBetween(-5, 5)).alias("n")))
query("sort_limit", "SELECT c_custkey FROM customer ORDER BY c_acctbal DESC, c_custkey LIMIT 10 OFFSET 5")(lambda s, d: table(s, d, "customer").orderBy(F.desc("c_acctbal"), "c_custkey").offset(5).limit(10).select("c_custkey"))
query("topk_nearest", "SELECT c_custkey FROM customer ORDER BY abs(c_acctbal - 1000), c_custkey LIMIT 7")(lambda s, d: table(s, d, "customer").orderBy(F.abs(c("c_acctbal") - 1000), "c_custkey").limit(7).select("c_custkey"))

# Sets and functions.

_A, _B = "SELECT c_nationkey k FROM customer WHERE c_acctbal > 5000", "SELECT s_nationkey k FROM supplier"


def _ab(s, d):
    return table(s, d, "customer").filter("c_acctbal > 5000").select(c("c_nationkey").alias("k")), table(s, d, "supplier").select(c("s_nationkey").alias("k"))


query("set_union", f"{_A} UNION ALL {_B}")(lambda s, d: (x := _ab(s, d))[0].unionByName(x[1]))
query("set_intersect", f"{_A} INTERSECT {_B}")(lambda s, d: (x := _ab(s, d))[0].intersect(x[1]))
query("set_except", f"{_A} EXCEPT ALL {_B}")(lambda s, d: (x := _ab(s, d))[0].exceptAll(x[1]))
query("fn_date", "SELECT o_orderkey, date_diff('day', DATE '1995-01-01', o_orderdate::DATE)::INT AS days, year(o_orderdate)::INT y FROM orders")(lambda s, d: table(s, d, "orders").select("o_orderkey", F.datediff("o_orderdate", F.lit("1995-01-01").cast("date")).alias("days"), F.year("o_orderdate").alias("y")))
query("fn_math", "SELECT c_custkey, floor(sqrt(abs(c_acctbal)))::BIGINT r, ceil(log2(c_custkey + 2))::BIGINT depth FROM customer")(lambda s, d: table(s, d, "customer").select("c_custkey", F.floor(F.sqrt(F.abs("c_acctbal"))).alias("r"), F.ceil(F.log2(c("c_custkey") + 2)).alias("depth")))
query("fn_array_dist", "SELECT vec_id, floor(list_sum(list_transform(embedding, lambda x: floor(x::DOUBLE * 1000)::BIGINT * floor(x::DOUBLE * 1000)::BIGINT)))::BIGINT n2 FROM embeddings")(lambda s, d: table(s, d, "embeddings").select("vec_id", F.aggregate(F.transform("embedding", lambda x: F.floor(x.cast("double") * 1000) * F.floor(x.cast("double") * 1000)), F.lit(0).cast("long"), lambda a, x: a + x).alias("n2")))
query("fn_explode_mean", "SELECT k::INT k, sum(floor(x::DOUBLE * 1000)::BIGINT)::BIGINT s FROM (SELECT unnest(embedding) x, generate_subscripts(embedding, 1) - 1 k FROM embeddings) GROUP BY 1")(lambda s, d: table(s, d, "embeddings").select(F.posexplode("embedding").alias("k", "x")).groupBy("k").agg(F.sum(F.floor(c("x").cast("double") * 1000)).alias("s")))
query("fn_map", "SELECT c_mktsegment, count(*) n FROM customer GROUP BY 1")(lambda s, d: table(s, d, "customer").groupBy("c_mktsegment").agg(F.count("*").alias("n")).agg(F.map_from_entries(F.collect_list(F.struct("c_mktsegment", "n"))).alias("m")).select(F.explode("m").alias("c_mktsegment", "n")))
query("fn_json", "SELECT event_id, (props->>'k')::BIGINT k FROM events")(lambda s, d: table(s, d, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k")))


@query("udtf_plan", f"SELECT points, l::INT AS level, (1 << l)::BIGINT regions, (n + (1 << l) - 1) // (1 << l) largest FROM ({core._SETS}) a, range(0, 40) t(l) WHERE l = 0 OR (n + (1 << (l - 1)) - 1) // (1 << (l - 1)) > 2000")
def udtf_plan(s, d):
    """Levels of the tree for the orders of each priority and a capacity, as a table function in SQL."""
    from pyspark.sql.functions import udtf

    class Plan:
        def eval(self, n: int, capacity: int):
            level, size = 0, n
            while True:
                yield level, 1 << level, size
                if size <= capacity:
                    break
                level, size = level + 1, (size + 1) // 2

    s.udtf.register("kmeans_plan", udtf(Plan, returnType="level int, regions long, largest long"))
    core.sets(s, d).createOrReplaceTempView("strata_sets")
    return s.sql("SELECT points, level, regions, largest FROM strata_sets, LATERAL kmeans_plan(n, 2000)")


@query("udf_nearest")
def udf_nearest(s, d):
    """Nearest centroid for SQL users, as an Arrow scalar function."""
    centres = np.array([[0.0, 0.0], [500_000.0, 500_000.0]])

    @F.pandas_udf("int")
    def nearest(a: pd.Series, b: pd.Series) -> pd.Series:
        d2 = (a.to_numpy()[:, None] - centres[:, 0]) ** 2 + (b.to_numpy()[:, None] - centres[:, 1]) ** 2
        return pd.Series(d2.argmin(1).astype("int32"))

    s.udf.register("nearest_centroid", nearest)
    table(s, d, "customer").createOrReplaceTempView("strata_customer")
    return s.sql("SELECT nearest_centroid(c_acctbal * 100, c_nationkey) AS cluster_id, count(*) AS n FROM strata_customer GROUP BY 1")


_NEAR = "SELECT c_custkey, CASE WHEN pow(round(c_acctbal * 100), 2) <= pow(round(c_acctbal * 100) - 500000, 2) THEN 0 ELSE 1 END k, least(pow(round(c_acctbal * 100), 2), pow(round(c_acctbal * 100) - 500000, 2)) d FROM customer"


@query("udaf_asse", f"SELECT k cluster_id, count(*) points, sum(floor(d)) / count(*) asse FROM ({_NEAR}) GROUP BY 1")
def udaf_asse(s, d):
    """The average error of a group and its size, as Arrow aggregates."""

    @F.pandas_udf("double")
    def asse(d2: pd.Series) -> float:
        return float(np.floor(d2.to_numpy()).sum() / len(d2))

    @F.pandas_udf("long")
    def points(d2: pd.Series) -> int:
        return len(d2)

    ps = ps_of(s, d, "customer2d")
    one = PointSet(ps.df.select("point_id", "c0"), 1)
    return assign.by_literal(one, np.array([[0.0], [500_000.0]])).groupBy("cluster_id").agg(points("dist2").alias("points"), asse("dist2").alias("asse"))


@query("cogroup_models", f"SELECT a.cluster_id, count(*) subsets, round(max(sqrt((a.c0 - b.c0) * (a.c0 - b.c0) + (a.c1 - b.c1) * (a.c1 - b.c1))), 3) largest_shift FROM ({core.chain('gauss3k', 6, 46, core._S1, core.T_GAUSS).select('SELECT subset_id, cluster_id::INT cluster_id, c0, c1 FROM cand')}) a JOIN ({core.plain('gauss3k', core._S1, core.T_GAUSS).select('SELECT cluster_id::INT cluster_id, c0, c1 FROM model')}) b USING (cluster_id) GROUP BY 1")
def cogroup_models(s, d):
    """The centroids of all subsets beside the baseline's, one cogroup for each cluster."""
    ps, cands = core.candidates(s, d, "gauss3k", 6, 46, core._S1, core.T_GAUSS)
    base = core.rows(s, kmeans.iterative_kmeans(ps, 4, kmeans.of_ids(ps, core._S1), max_iter=core.T_GAUSS).centroids)

    def compare(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        far = np.sqrt(((a[["c0", "c1"]].to_numpy() - b[["c0", "c1"]].to_numpy()) ** 2).sum(1)).max()
        return pd.DataFrame({"cluster_id": a.cluster_id.iloc[:1], "subsets": [len(a)], "largest_shift": [round(far, 3)]})

    return cands.select("cluster_id", "c0", "c1").groupBy("cluster_id").cogroup(base.groupBy("cluster_id")).applyInPandas(compare, "cluster_id int, subsets long, largest_shift double")


@query("sql_registered", "SELECT c1 AS nation, count(*) AS n FROM (SELECT round(c_acctbal * 100)::BIGINT c0, c_nationkey::BIGINT c1 FROM customer) WHERE c0 >= 250000 GROUP BY 1")
def sql_registered(s, d):
    """Points and model as views, and a statement with a parameter."""
    views = files.register(s, ps_of(s, d, "customer2d"), np.array([[0.0, 0.0], [500_000.0, 10.0]]), "strata_c")
    got = s.sql(f"SELECT c1 AS nation, count(*) AS n FROM {views['points']} WHERE c0 >= (SELECT :share * max(c0) FROM {views['model']}) GROUP BY 1", args={"share": 0.5})
    return got


@query("win_lag_sse_rounds", core.plain("gauss3k", core.INITIAL[5], core.T_GAUSS).select("SELECT round, sse, sse - lag(sse) OVER (ORDER BY round) change FROM (" + " UNION ALL ".join(f"SELECT {r} round, sum(floor(b.d)::BIGINT)::BIGINT sse FROM a{r}" for r in range(1, 6)) + ")"))
def win_lag_sse_rounds(s, d):
    """The change of the error from round to round."""
    ps = ps_of(s, d, "gauss3k")
    r = kmeans.iterative_kmeans(ps, 4, kmeans.of_ids(ps, core.INITIAL[5]), max_iter=5)
    return s.createDataFrame([(n, e) for n, e, _ in r.trace], "round int, sse long").withColumn("change", F.col("sse") - F.lag("sse").over(Window.orderBy("round")))


@query("agg_rollup_grid")
def agg_rollup_grid(s, d):
    """The option grid's errors, averaged over fewer and fewer options."""
    return core.grid_sse(s, d).rollup("partition", "labels", "how").agg(F.count("*").alias("runs"), F.avg("sse").alias("sse"))


# Streams, run to their end.

_CENTRES = np.array([[1000.0, 10_000.0], [5000.0, 40_000.0], [15_000.0, 70_000.0]])
_SCORED = "(SELECT event_id, ts, CASE WHEN d0 <= d1 AND d0 <= d2 THEN 0 WHEN d1 <= d2 THEN 1 ELSE 2 END cluster_id, c0, c1 FROM (SELECT *, " + ", ".join(f"(c0 - {a!r}) * (c0 - {a!r}) + (c1 - {b!r}) * (c1 - {b!r}) d{k}" for k, (a, b) in enumerate(_CENTRES.tolist())) + " FROM (SELECT event_id, ts, round(value * 100)::BIGINT c0, (hour(ts) * 3600 + minute(ts) * 60 + second(ts))::BIGINT c1 FROM events)))"


def _name() -> str:
    return "strata_" + uuid.uuid4().hex


query("stream_score", f"SELECT event_id point_id, cluster_id FROM {_SCORED}")(lambda s, d: ev.run_to_end(ev.score(ev.stream(s, d), _CENTRES).select("point_id", "cluster_id"), _name()))
query("stream_tumbling", f"SELECT epoch_us(time_bucket(INTERVAL 1 HOUR, ts)) start_us, cluster_id, count(*) n FROM {_SCORED} GROUP BY 1, 2")(lambda s, d: ev.run_to_end(ev.counts(ev.score(ev.stream(s, d), _CENTRES), "1 hour"), _name(), "complete"))
query("stream_sliding", f"SELECT epoch_us(time_bucket(INTERVAL 1 HOUR, ts) - k * INTERVAL 1 HOUR) start_us, cluster_id, count(*) n FROM {_SCORED}, (SELECT unnest([0, 1]) k) GROUP BY 1, 2")(lambda s, d: ev.run_to_end(ev.counts(ev.score(ev.stream(s, d), _CENTRES), "2 hours", "1 hour"), _name(), "complete"))
query("stream_session", "WITH g AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) k FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END new FROM events)) SELECT user_id, epoch_us(min(ts)) start_us, count(*) n FROM g GROUP BY user_id, k")(lambda s, d: ev.run_to_end(ev.sessions(ev.stream(s, d)), _name(), "complete"))
query("stream_dedup", "SELECT event_id FROM events")(lambda s, d: ev.run_to_end(ev.deduplicated(ev.stream(s, d)).select("event_id"), _name()))
query("stream_running_centroids", f"SELECT cluster_id, count(*) n, sum(c0)::BIGINT s_c0, sum(c1)::BIGINT s_c1 FROM {_SCORED} GROUP BY 1")(lambda s, d: ev.run_to_end(ev.running_sums(ev.stream(s, d), _CENTRES), _name(), "complete"))
query("stream_static_join", "SELECT c_mktsegment, count(*) n FROM events JOIN customer ON c_custkey = user_id GROUP BY 1")(lambda s, d: ev.run_to_end(ev.stream(s, d).join(table(s, d, "customer").select("c_custkey", "c_mktsegment"), F.col("user_id") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n")), _name(), "complete"))
