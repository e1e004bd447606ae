"""Labels: each region deals its points out to subsets, one per label."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

RAGGED = ("proportional", "keep", "drop", "guard")


def hashed(seed: int, point_id: str = "point_id") -> Column:
    """An order that looks random and is alike in every run and engine."""
    return F.md5(F.concat_ws(":", F.lit(str(seed)), F.col(point_id).cast("string")))


def _dealt(df: DataFrame, order: list, subsets: int | None, ragged: str) -> DataFrame:
    if ragged not in RAGGED:
        raise ValueError(f"ragged is one of {RAGGED}")
    w = Window.partitionBy("region_id")
    df = df.withColumn("_rank", F.row_number().over(w.orderBy(*order)).cast("long")).withColumn("_len", F.count("*").over(w))
    if ragged == "proportional":
        label = F.floor((F.col("_rank") - 1) * subsets / F.col("_len")) + 1
        df = df.withColumn("label", label.cast("long"))
    else:
        df = df.withColumn("label", F.col("_rank"))
        if ragged == "drop":
            df = df.filter(F.col("label") <= subsets)
    return df.drop("_rank", "_len")


def by_axis(df: DataFrame, axis: int = 0, subsets: int | None = None, ragged: str = "keep") -> DataFrame:
    """Numbers along an axis. `keep` gives the last labels to larger regions only, `drop` leaves labels over
    `subsets` out, `proportional` spreads every region over exactly `subsets` labels."""
    return _dealt(df, [f"c{axis}", "point_id"], subsets, ragged)


def by_random(df: DataFrame, seed: int = 0, subsets: int | None = None, ragged: str = "keep") -> DataFrame:
    """A permutation of each region that a seed decides."""
    return _dealt(df, [hashed(seed), "point_id"], subsets, ragged)


def subset(df: DataFrame, label: int) -> DataFrame:
    return df.filter(F.col("label") == label)


def random_partition(df: DataFrame, subsets: int, seed: int = 0, parts: int = 4096) -> DataFrame:
    """No tree: all points dealt out in hash order, subsets of sizes at most one apart. Ranks come from
    counts per hash part and ranks inside the parts, so no task sees all rows."""
    h = hashed(seed)
    df = df.withColumn("_h", h).withColumn("_part", F.conv(F.substring("_h", 1, 3), 16, 10).cast("int"))
    sizes = df.groupBy("_part").agg(F.count("*").alias("_n"))
    offsets = sizes.select("_part", (F.sum("_n").over(Window.orderBy("_part")) - F.col("_n")).alias("_before"))  # at most 4096 rows
    rank = F.row_number().over(Window.partitionBy("_part").orderBy("_h", "point_id")) - 1
    out = df.withColumn("_rank", rank).join(F.broadcast(offsets), "_part")
    return out.withColumn("label", (F.pmod(F.col("_before") + F.col("_rank"), F.lit(subsets)) + 1).cast("long")).drop("_h", "_part", "_rank", "_before")


def prethin(df: DataFrame, n: int, wanted: int, seed: int = 0) -> DataFrame:
    """A hash sample of about `wanted` of `n` points, before anything is shuffled."""
    top = min(1 << 32, -(-(wanted << 32) // max(1, n)))
    return df.filter(F.conv(F.substring(hashed(seed), 1, 8), 16, 10).cast("long") < top)
