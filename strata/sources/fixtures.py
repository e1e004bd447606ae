"""Gaussian mixtures from hashes: the same integers in every engine, and as a Spark data source."""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from strata.functions.points import PointSet, table

#: Standard deviation of the noise, and centres of the four clusters in its units.
UNIT = 53_510
CENTRES = ((0, 0), (9, 1), (2, 9), (10, 10))
SEED = 7
#: Ids of the points whose coordinates start each experiment.
INITIAL = {1: (3, 1, 40, 77), 2: (0, 4, 8, 1), 3: (5, 6, 7, 8), 4: (100, 200, 301, 402), 5: (11, 22, 33, 44)}


def noise(seed: int, point_id: Column, axis: str) -> Column:
    """The sum of eight 16-bit parts of an md5, less its mean."""
    h = F.md5(F.concat_ws(":", F.lit(str(seed)), point_id.cast("string"), F.lit(axis)))
    total = F.lit(-262_140).cast("long")
    for first, parts in ((0, 3), (3, 3), (6, 2)):  # converted by threes, which costs half
        x = F.conv(F.substring(h, 4 * first + 1, 4 * parts), 16, 10).cast("long")
        for k in range(parts):
            total = total + F.shiftright(x, 16 * k).bitwiseAND(F.lit(65_535))
    return total


def gauss(keys: DataFrame, key: str, seed: int = SEED) -> PointSet:
    i = F.col(key).cast("long")
    truth = F.pmod(i, F.lit(len(CENTRES)))
    at = lambda a: F.element_at(F.array(*(F.lit(c[a] * UNIT) for c in CENTRES)), (truth + 1).cast("int")).cast("long")
    return PointSet(keys.select(i.alias("point_id"), (at(0) + 2 * noise(seed, i, "x")).alias("c0"), (at(1) + 2 * noise(seed, i, "y")).alias("c1"), truth.cast("int").alias("truth")), 2)


def gauss3k(spark: SparkSession, sf_dir: str) -> PointSet:
    return gauss(table(spark, sf_dir, "events").filter("event_id < 3000").select("event_id"), "event_id")


def gauss_events(spark: SparkSession, sf_dir: str) -> PointSet:
    return gauss(table(spark, sf_dir, "events").select("event_id"), "event_id")


def gauss15k(spark: SparkSession, sf_dir: str) -> PointSet:
    return gauss(table(spark, sf_dir, "orders").select("o_orderkey"), "o_orderkey")


def gauss_row(i: int, seed: int = SEED) -> tuple[int, int, int, int]:
    """One point, without Spark."""
    n = [sum(int(h[k : k + 4], 16) for k in range(0, 32, 4)) - 262_140 for h in (hashlib.md5(f"{seed}:{i}:{a}".encode()).hexdigest() for a in "xy")]
    x, y = CENTRES[i % len(CENTRES)]
    return i, x * UNIT + 2 * n[0], y * UNIT + 2 * n[1], i % len(CENTRES)


class GaussSource(DataSource):
    """`spark.read.format("strata_gauss").option("rows", n)`: n points of the mixture from the id `first` (0) on, in `parts` partitions."""

    @classmethod
    def name(cls) -> str:
        return "strata_gauss"

    def schema(self) -> str:
        return "point_id long, c0 long, c1 long, truth int"

    def reader(self, schema) -> "GaussReader":
        return GaussReader(int(self.options.get("rows", 1000)), int(self.options.get("parts", 4)), int(self.options.get("seed", SEED)), int(self.options.get("first", 0)))


class GaussReader(DataSourceReader):
    def __init__(self, rows: int, parts: int, seed: int, first: int = 0):
        self.rows, self.parts, self.seed, self.first = rows, parts, seed, first

    def partitions(self):
        return [InputPartition(k) for k in range(self.parts)]

    def read(self, partition):
        for i in range(partition.value, self.rows, self.parts):
            yield gauss_row(self.first + i, self.seed)
