"""Point sets: a table of `point_id` and integer or double coordinates `c0`..`c{d-1}`."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


@dataclass(frozen=True)
class PointSet:
    df: DataFrame
    d: int

    @property
    def coords(self) -> list[str]:
        return [f"c{k}" for k in range(self.d)]

    @staticmethod
    def from_df(df: DataFrame, point_id: Column | str, coords: Sequence[Column], on_bad: str = "error", validate: bool = False) -> "PointSet":
        """`on_bad` says whether null, NaN and infinite coordinates stop the job or drop their rows."""
        out = df.select(F.col(point_id).alias("point_id") if isinstance(point_id, str) else point_id.alias("point_id"), *(c.alias(f"c{k}") for k, c in enumerate(coords)))
        ps = PointSet(clean(out, len(coords), on_bad), len(coords))
        if validate and ps.df.groupBy("point_id").count().filter("count > 1").limit(1).count():
            raise ValueError("point_id is not unique; the order of points needs unique ids")
        return ps

    def count(self) -> int:
        return self.df.count()


def clean(df: DataFrame, d: int, on_bad: str) -> DataFrame:
    ok = F.col("point_id").isNotNull()
    for k in range(d):
        c = F.col(f"c{k}")
        ok = ok & c.isNotNull()
        if dict(df.dtypes)[f"c{k}"] in ("double", "float"):
            ok = ok & ~F.isnan(c) & (F.abs(c) < float("inf"))
    if on_bad == "drop":
        return df.filter(ok)
    if on_bad != "error":
        raise ValueError("on_bad is 'error' or 'drop'")
    first = df.columns[0]
    return df.withColumn(first, F.when(ok, F.col(first)).otherwise(F.raise_error(F.lit("null, NaN or infinite coordinate"))))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def cents(c: str) -> Column:
    return F.round(F.col(c) * 100).cast("long")


def _numbered(df: DataFrame, order: Sequence[str], parts: int = 64) -> DataFrame:
    """Ids from the total order of rows: ranges of the first column by sampled bounds, ranks within each, and an offset
    from the counts of the ranges before, so no task sees all rows."""
    bounds = sorted({x for x in df.select(F.percentile_approx(order[0], [k / parts for k in range(1, parts)], 1000)).first()[0] or []})
    low = F.lit(0)
    for x in bounds:
        low = low + F.when(F.col(order[0]) > F.lit(x), 1).otherwise(0)
    ranged = df.withColumn("_part", low)
    sizes = ranged.groupBy("_part").agg(F.count("*").alias("_n"))
    before = sizes.select("_part", (F.sum("_n").over(Window.orderBy("_part")) - F.col("_n")).alias("_before"))  # at most `parts` rows
    rank = F.row_number().over(Window.partitionBy("_part").orderBy(*order))
    numbered = ranged.withColumn("_rank", rank).join(F.broadcast(before), "_part")
    return numbered.withColumn("point_id", (F.col("_before") + F.col("_rank")).cast("long")).drop("_part", "_rank", "_before")


def featurized(spark: SparkSession, sf_dir: str, fixture: str) -> PointSet:
    """The named point sets over the given tables."""
    t = lambda name: table(spark, sf_dir, name)
    c = F.col
    if fixture == "orders2d":
        return PointSet.from_df(t("orders"), "o_orderkey", [cents("o_totalprice"), F.datediff("o_orderdate", F.lit("1995-01-01").cast("date")).cast("long")])
    if fixture == "lineitem2d":
        df = t("lineitem")
        return PointSet.from_df(_numbered(df, df.columns), "point_id", [c("l_quantity").cast("long"), cents("l_extendedprice")])
    if fixture == "events2d":
        ts = c("ts")
        return PointSet.from_df(t("events"), "event_id", [cents("value"), (F.hour(ts) * 3600 + F.minute(ts) * 60 + F.second(ts)).cast("long")])
    if fixture == "customer2d":
        return PointSet.from_df(t("customer"), "c_custkey", [cents("c_acctbal"), c("c_nationkey").cast("long")])
    if fixture == "supplier1d":
        return PointSet.from_df(t("supplier"), "s_suppkey", [cents("s_acctbal")])
    if fixture == "part2d":
        return PointSet.from_df(t("part"), "p_partkey", [c("p_size").cast("long"), cents("p_retailprice")])
    if fixture in ("embed8", "embed64"):
        return PointSet.from_df(t("embeddings"), "vec_id", [F.floor(F.get("embedding", F.lit(k)).cast("double") * 1_000_000).cast("long") for k in range(int(fixture[5:]))])
    if fixture == "docs2d":
        return PointSet.from_df(t("documents"), "doc_id", [c("n_chars").cast("long"), F.size(F.split("text", " ", -1)).cast("long")])
    if fixture == "pages2d":
        return PointSet.from_df(t("pages"), "page_id", [F.length("html").cast("long"), F.length("url").cast("long")])
    if fixture == "turns2d":
        return PointSet.from_df(t("conversations"), c("conv_id") * 10_000 + c("turn"), [F.coalesce(F.length("text"), F.lit(0)).cast("long"), F.size(F.split(F.coalesce("text", F.lit("")), " ", -1)).cast("long")])
    if fixture == "nation1d":
        return PointSet.from_df(t("nation"), c("n_nationkey").cast("long"), [c("n_regionkey").cast("long")])
    if fixture == "region1d":
        return PointSet.from_df(t("region"), c("r_regionkey").cast("long"), [c("r_regionkey").cast("long")])
    if fixture == "line8":
        return PointSet.from_df(spark.range(8), "id", [c("id") + 1])
    raise KeyError(fixture)


def lengths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(source, id, c0, c1): code points and words of the texts of several tables."""
    parts = [table(spark, sf_dir, name).select(F.lit(name).alias("source"), F.col(key).cast("long").alias("id"), F.length(text).cast("long").alias("c0"), F.size(F.split(text, " ", -1)).cast("long").alias("c1")) for name, key, text in (("pages", "page_id", "html"), ("benchmark", "item_id", "text"))]
    return parts[0].union(parts[1])


def scaled(ps: PointSet, how: str) -> PointSet:
    """Min-max or z-score scaling by one global aggregate, whose single row is joined to all."""
    if how == "none":
        return ps
    if how == "minmax":
        parts = [x for c in ps.coords for x in (F.min(c).alias(f"a_{c}"), (F.max(c) - F.min(c)).alias(f"b_{c}"))]
    else:
        parts = [x for c in ps.coords for x in (F.avg(c).alias(f"a_{c}"), F.stddev_pop(c).alias(f"b_{c}"))]
    one = ps.df.agg(*parts)
    out = ps.df.crossJoin(F.broadcast(one))  # one row
    return PointSet(out.select("point_id", *(F.coalesce((F.col(c) - F.col(f"a_{c}")) / F.nullif(F.col(f"b_{c}").cast("double"), F.lit(0.0)), F.lit(0.0)).alias(c) for c in ps.coords)), ps.d)
