"""From the candidates of all subsets to K centroids."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Candidates up to which the pairs are merged on the driver.
MOST_CANDIDATES = 4_000


def hierarchical_array(c: np.ndarray, k: int, weights: np.ndarray | None = None) -> np.ndarray:
    """The nearest two become their midpoint (or weighted mean) until `k` remain. Ties take the pair that was
    numbered first; each midpoint gets the next number."""
    return hierarchical_weighted(c, k, weights, weights is not None)[0]


def hierarchical_weighted(c: np.ndarray, k: int, weights: np.ndarray | None, weighted: bool) -> tuple[np.ndarray, np.ndarray]:
    """What remains, and the sum of the weights behind each."""
    c = np.asarray(c, float)
    if len(c) <= k:
        return c, np.ones(len(c)) if weights is None else np.asarray(weights, float)
    n, d = c.shape
    # one slot for each number; `least` and `mate` are a slot's nearest later one, so that the pair of least (distance, first,
    # second) is the first slot of least distance
    x = np.zeros((2 * n, d))
    x[:n] = c
    weight = np.ones(2 * n)
    if weights is not None:
        weight[:n] = weights
    least, mate = np.full(2 * n, np.inf), np.full(2 * n, -1)
    there = np.arange(n)

    def against(slot, others):
        d2 = np.zeros(len(others))
        for a in range(d):
            diff = x[others, a] - x[slot, a]
            d2 += diff * diff
        return d2

    def look(slot, later):
        if not len(later):
            least[slot], mate[slot] = np.inf, -1
            return
        d2 = against(slot, later)
        at = int(d2.argmin())
        least[slot], mate[slot] = d2[at], later[at]

    for at in range(n):
        look(at, there[at + 1 :])
    for new in range(n, 2 * n - k):
        i = int(there[least[there].argmin()])
        j = int(mate[i])
        both = weight[i] + weight[j]
        x[new] = (x[i] * weight[i] + x[j] * weight[j]) / both if weighted and both else (x[i] + x[j]) / 2
        weight[new] = both
        there = there[(there != i) & (there != j)]
        d2 = against(new, there)
        widowed = np.flatnonzero((mate[there] == i) | (mate[there] == j))
        nearer = d2 < least[there]  # an equal one keeps its earlier mate
        least[there[nearer]], mate[there[nearer]] = d2[nearer], new
        there = np.append(there, new)
        for at in widowed:
            look(there[at], there[at + 1 :])
    return x[there], weight[there]


def hierarchical(candidates: DataFrame, k: int, d: int, weighted: bool = False) -> np.ndarray:
    rows = candidates.orderBy("subset_id", "cluster_id").limit(MOST_CANDIDATES + 1).collect()
    if len(rows) > MOST_CANDIDATES:
        raise ValueError(f"over {MOST_CANDIDATES} candidates: use hierarchical_grouped, min_asse, or fewer subsets")
    c = np.array([[r[f"c{i}"] for i in range(d)] for r in rows])
    return hierarchical_array(c, k, np.array([r["members"] for r in rows]) if weighted else None)


def hierarchical_grouped(candidates: DataFrame, k: int, d: int, weighted: bool = True, fan_in: int = 2_000) -> np.ndarray:
    """Merging in rounds, for any number of candidates: groups of whole subsets, of about `fan_in` candidates each, are
    merged to `k` by one task per group, and what they give is merged again, until one group is left. The weights
    of a round are the points behind each centroid, so weighted means stay means of points."""
    coords = [f"c{i}" for i in range(d)]
    schema = "number long, cluster_id int, members long, " + ", ".join(f"{c} double" for c in coords)
    rows = candidates.select(F.col("subset_id").alias("number"), "cluster_id", "members", *coords)
    subsets = candidates.agg(F.count_distinct("subset_id")).first()[0]
    per_group = max(2, fan_in // k)

    def merged(group):
        import pandas as pd

        group = group.sort_values(["number", "cluster_id"])
        x, w = group[coords].to_numpy(float), group.members.to_numpy(float)
        if len(x) > k:
            x, w = hierarchical_weighted(x, k, w, weighted)
        return pd.DataFrame({"number": int(group.group.iloc[0]), "cluster_id": np.arange(len(x)), "members": w.astype("int64"), **{c: x[:, i] for i, c in enumerate(coords)}})

    while subsets > per_group:
        groups = -(-subsets // per_group)
        dense = F.dense_rank().over(Window.orderBy("number")) - 1 if subsets <= MOST_CANDIDATES else F.pmod(F.xxhash64("number"), F.lit(groups))
        rows = rows.withColumn("group", F.pmod(dense, F.lit(groups)).cast("long")).groupBy("group").applyInPandas(merged, schema)
        subsets = groups
    got = rows.orderBy("number", "cluster_id").collect()
    x, w = np.array([[r[c] for c in coords] for r in got]), np.array([float(r.members) for r in got])
    return hierarchical_weighted(x, k, w, weighted)[0] if len(x) > k else x


def hierarchical_distributed(candidates: DataFrame, k: int, d: int, weighted: bool = False) -> np.ndarray:
    """The same steps as `hierarchical`, one distributed search of the nearest pair for each: for candidates that
    are to stay where they are. It takes as many jobs as there are candidates over `k`."""
    coords = [f"c{i}" for i in range(d)]
    w = Window.orderBy("subset_id", "cluster_id")
    rows = candidates.select((F.row_number().over(w) - 1).cast("long").alias("id"), *coords, F.col("members").cast("double").alias("w")).persist()
    n = rows.count()
    gone: list[int] = []
    added: list[tuple] = []
    schema = "id long, " + ", ".join(f"{c} double" for c in coords) + ", w double"
    for step in range(n - k):
        now = rows.filter(~F.col("id").isin(gone)) if gone else rows
        fresh = [r for r in added if r[0] not in gone]
        now = now.union(rows.sparkSession.createDataFrame(fresh, schema)) if fresh else now
        p = closest_pair(now, d).first()
        pair = {r.id: r for r in now.filter(F.col("id").isin([p.i, p.j])).collect()}
        a, b = pair[p.i], pair[p.j]
        both = a.w + b.w
        middle = [(a[c] * a.w + b[c] * b.w) / both if weighted else (a[c] + b[c]) / 2 for c in coords]
        gone += [p.i, p.j]
        added.append((n + step, *middle, both))
    left = [r for r in rows.filter(~F.col("id").isin(gone)).collect()] if gone else rows.collect()
    out = sorted([(r.id, *(r[c] for c in coords)) for r in left] + [r[: d + 1] for r in added if r[0] not in gone])
    rows.unpersist()
    return np.array([r[1:] for r in out])


def best_subset(candidates: DataFrame, min_members: int = 0) -> DataFrame:
    """One row: the subset of least average error, the lowest id among equals."""
    whole = candidates.groupBy("subset_id").agg(F.min("asse").alias("asse"), F.sum("members").alias("members")).filter(F.col("members") >= min_members)
    return whole.agg(F.min(F.struct("asse", "subset_id")).alias("best")).select("best.asse", "best.subset_id")


def min_asse(candidates: DataFrame, d: int, min_members: int = 0) -> np.ndarray:
    rows = candidates.join(F.broadcast(best_subset(candidates, min_members).select("subset_id")), "subset_id").orderBy("cluster_id").collect()
    return np.array([[r[f"c{i}"] for i in range(d)] for r in rows])


def closest_pair(points: DataFrame, d: int) -> DataFrame:
    """The nearest two rows of (id, c*): one step of merging, for candidates that stay distributed."""
    b = points.select(F.col("id").alias("j"), *(F.col(f"c{k}").alias(f"b{k}") for k in range(d)))
    d2 = sum(((F.col(f"c{k}") - F.col(f"b{k}")) * (F.col(f"c{k}") - F.col(f"b{k}")) for k in range(1, d)), (F.col("c0") - F.col("b0")) * (F.col("c0") - F.col("b0")))
    return points.join(b, F.col("id") < F.col("j")).agg(F.min(F.struct(d2.alias("dist2"), F.col("id").alias("i"), F.col("j"))).alias("p")).select("p.i", "p.j", "p.dist2")
