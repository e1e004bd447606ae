"""The nearest centroid of each point, in several physical forms with the same answer; ties go to the lowest cluster."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from strata.functions.points import PointSet


def centroid_table(spark: SparkSession, c: np.ndarray) -> DataFrame:
    d = c.shape[1]
    return spark.createDataFrame([(k, *map(float, row)) for k, row in enumerate(c)], "cluster_id int, " + ", ".join(f"x{k} double" for k in range(d)))


def distance2(cols: Sequence[Column], row: Sequence) -> Column:
    total = None
    for a, b in zip(cols, row, strict=True):
        d = a - (b if isinstance(b, Column) else F.lit(float(b)))
        total = d * d if total is None else total + d * d
    return total


def nearest(cols: Sequence[Column], c: np.ndarray) -> Column:
    """struct(dist2, cluster_id), as one expression of literals."""
    return F.array_min(F.array(*(F.struct(distance2(cols, row).alias("dist2"), F.lit(k).alias("cluster_id")) for k, row in enumerate(c))))


def by_literal(ps: PointSet, c: np.ndarray) -> DataFrame:
    """No join and no shuffle; the centroids are literals in the generated code."""
    n = nearest([F.col(x) for x in ps.coords], c)
    return ps.df.withColumn("_n", n).withColumn("cluster_id", F.col("_n.cluster_id")).withColumn("dist2", F.col("_n.dist2")).drop("_n")


def by_join(ps: PointSet, c: np.ndarray) -> DataFrame:
    """The reference form: points by K centroids (a driver-side array, so broadcast), then the least per point."""
    pairs = ps.df.crossJoin(F.broadcast(centroid_table(ps.df.sparkSession, c)))
    d2 = distance2([F.col(x) for x in ps.coords], [F.col(f"x{k}") for k in range(ps.d)])
    best = pairs.groupBy("point_id", *ps.coords).agg(F.min(F.struct(d2.alias("dist2"), F.col("cluster_id"))).alias("n"))
    return best.select("point_id", *ps.coords, "n.cluster_id", "n.dist2")


def by_hof(ps: PointSet, c: np.ndarray) -> DataFrame:
    """Higher-order functions over one array column, for wide points and few centroids."""
    v = F.array(*(F.col(x).cast("double") for x in ps.coords))

    def d2(row):
        return F.aggregate(F.zip_with(v, F.array(*map(F.lit, map(float, row))), lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, x: s + x)

    n = F.array_min(F.array(*(F.struct(d2(row).alias("dist2"), F.lit(k).alias("cluster_id")) for k, row in enumerate(c))))
    return ps.df.withColumn("_n", n).select(*ps.df.columns, "_n.cluster_id", "_n.dist2")


def by_arrow(ps: PointSet, c: np.ndarray, chunk: int = 65_536) -> DataFrame:
    """Numpy on Arrow batches, for many centroids or dimensions."""
    coords = ps.coords
    fields = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in ps.df.schema)

    def kernel(batches):
        import numpy as np

        for pdf in batches:
            x = pdf[coords].to_numpy(float)
            d = np.zeros((len(x), len(c)))
            for k in range(x.shape[1]):
                diff = x[:, k, None] - c[None, :, k]
                d += diff * diff
            best = d.argmin(1) if len(x) else np.zeros(0, int)
            yield pdf.assign(cluster_id=best.astype("int32"), dist2=d[np.arange(len(x)), best])

    return ps.df.mapInPandas(kernel, fields + ", cluster_id int, dist2 double")


#: Regions times centroids up to which the lists of centroids by region are broadcast.
MOST_LISTED = 1_000_000


def boxes_of(ps: PointSet, regions: DataFrame) -> DataFrame:
    return regions.groupBy("region_id").agg(*(f(x).alias(f"{n}_{x}") for x in ps.coords for n, f in (("lo", F.min), ("hi", F.max))))


def by_cells(ps: PointSet, regions: DataFrame, c: np.ndarray, boxes: DataFrame | None = None) -> DataFrame:
    """Centroids pruned per region by its bounding box: those that some other centroid beats at every corner are
    not compared. Regions carry lists, which meet the points in a join on the region: a broadcast one while regions
    times centroids stay under MOST_LISTED. `boxes` spares a look for them in every round."""
    boxes = boxes_of(ps, regions) if boxes is None else boxes

    def far(row):
        return sum((F.pow(F.greatest(F.abs(F.col(f"lo_{x}") - float(v)), F.abs(F.col(f"hi_{x}") - float(v))), F.lit(2)) for x, v in zip(ps.coords, row, strict=True)), F.lit(0.0))

    def near(row):
        return sum((F.pow(F.greatest(F.col(f"lo_{x}") - float(v), F.lit(float(v)) - F.col(f"hi_{x}"), F.lit(0.0)), F.lit(2)) for x, v in zip(ps.coords, row, strict=True)), F.lit(0.0))

    most = F.array_min(F.array(*(far(row) for row in c))) * (1 + 1e-9)
    lists = boxes.withColumn("_most", most).select("region_id", F.array_compact(F.array(*(F.when(near(row) <= F.col("_most"), F.struct(F.lit(k).alias("k"), *(F.lit(float(v)).alias(f"x{i}") for i, v in enumerate(row)))) for k, row in enumerate(c)))).alias("_cands"))
    if boxes.count() * len(c) <= MOST_LISTED:
        lists = F.broadcast(lists)
    d2 = lambda s: distance2([F.col(x) for x in ps.coords], [s[f"x{k}"] for k in range(ps.d)])
    joined = regions.join(lists, "region_id")
    n = F.array_min(F.transform("_cands", lambda s: F.struct(d2(s).alias("dist2"), s["k"].alias("cluster_id"))))
    return joined.withColumn("_n", n).select(*ps.df.columns, "_n.cluster_id", "_n.dist2")


def sums(assigned: DataFrame, coords: Sequence[str]) -> DataFrame:
    return assigned.groupBy("cluster_id").agg(F.count("*").alias("n"), *(F.sum(x).alias(f"s_{x}") for x in coords))
