"""Point files, labelled data, and models on storage that Spark can reach."""

from __future__ import annotations

import json

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from strata.functions.points import PointSet

FORMATS = ("parquet", "orc", "json", "csv", "text")


def read_points(spark: SparkSession, path: str, fmt: str, d: int, kind: str = "double", on_bad: str = "error") -> PointSet:
    """Files of point_id and c0..c{d-1}; a text file has them in each line, separated by white space."""
    if fmt not in FORMATS:
        raise ValueError(f"format is one of {FORMATS}")
    schema = "point_id long, " + ", ".join(f"c{k} {kind}" for k in range(d))
    if fmt == "text":
        parts = F.split(F.trim("value"), r"\s+")
        lines = spark.read.text(path).select(parts.alias("p"))
        df = lines.select(F.get("p", F.lit(0)).try_cast("long").alias("point_id"), *(F.get("p", F.lit(k + 1)).try_cast(kind).alias(f"c{k}") for k in range(d)))
    else:
        df = spark.read.schema(schema).format(fmt).load(path)
    return PointSet.from_df(df, "point_id", [F.col(f"c{k}") for k in range(d)], on_bad)


def write_labelled(labelled: DataFrame, path: str, most_folders: int = 10_000) -> None:
    """A folder per subset, so that reading one subset prunes the others; sorted inside for narrow row groups."""
    n = labelled.agg(F.max("label")).first()[0] or 0
    if n > most_folders:
        raise ValueError(f"{n} folders: use write_bucketed")
    labelled.repartition("label").sortWithinPartitions("label", "point_id").write.mode("overwrite").partitionBy("label").parquet(path)


def write_bucketed(labelled: DataFrame, name: str, buckets: int) -> None:
    """A table whose buckets keep each subset together, for many subsets."""
    labelled.write.mode("overwrite").bucketBy(buckets, "label").sortBy("label", "point_id").saveAsTable(name)


def save_model(spark: SparkSession, c: np.ndarray, path: str, **about) -> None:
    rows = [(k, *map(float, r)) for k, r in enumerate(c)]
    schema = "cluster_id int, " + ", ".join(f"c{k} double" for k in range(c.shape[1]))
    spark.createDataFrame(rows, schema).coalesce(1).write.mode("overwrite").parquet(f"{path}/centroids")
    spark.createDataFrame([(json.dumps({"k": len(c), "d": int(c.shape[1])} | about),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/about")


def load_model(spark: SparkSession, path: str) -> tuple[np.ndarray, dict]:
    rows = spark.read.parquet(f"{path}/centroids").orderBy("cluster_id").collect()
    return np.array([list(r)[1:] for r in rows]), json.loads(spark.read.text(f"{path}/about").first()[0])


def register(spark: SparkSession, ps: PointSet, c: np.ndarray, name: str) -> dict[str, str]:
    """Temporary views of the points and of the model, by name."""
    views = {"points": f"{name}_points", "model": f"{name}_model"}
    ps.df.createOrReplaceTempView(views["points"])
    spark.createDataFrame([(k, *map(float, row)) for k, row in enumerate(c)], "cluster_id int, " + ", ".join(f"c{i} double" for i in range(c.shape[1]))).createOrReplaceTempView(views["model"])
    return views
