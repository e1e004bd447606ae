"""The whole method, its variants, and the baselines."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from strata.functions.points import PointSet
from strata.operators import assign, kdtree, labeling, localsolver, merge, subset


#: Points up to which `tree='auto'` shuffles them once a level.
AUTO_EXACT = 1_000_000


@dataclass
class Result:
    centroids: np.ndarray
    candidates: DataFrame | None = None
    labelled: DataFrame | None = None
    trace: list[tuple[int, int, float]] = field(default_factory=list)
    rounds: int = 0

    def predict(self, ps: PointSet) -> DataFrame:
        return assign.by_literal(ps, self.centroids)

    def release(self) -> None:
        """Gives back what holds the candidates."""
        if self.candidates is not None:
            self.candidates.unpersist()


def explicit(points: Sequence[Sequence[float]]) -> np.ndarray:
    return np.array(points, float)


def of_ids(ps: PointSet, ids: Sequence[int]) -> np.ndarray:
    """The coordinates of the named points, in the order of `ids`."""
    rows = {r.point_id: r for r in ps.df.filter(F.col("point_id").isin(list(ids))).collect()}
    return np.array([[rows[i][c] for c in ps.coords] for i in ids], float)


def first_k(ps: PointSet, k: int) -> np.ndarray:
    return np.array([[r[c] for c in ps.coords] for r in ps.df.orderBy("point_id").limit(k).collect()], float)


def random_k(ps: PointSet, k: int, seed: int = 0) -> np.ndarray:
    return np.array([[r[c] for c in ps.coords] for r in ps.df.orderBy(labeling.hashed(seed), "point_id").limit(k).collect()], float)


def labelled(ps: PointSet, depth: int, subsets: int | None = None, partition: str = "tree", labels: str = "axis", label_axis: int = 0, ragged: str = "keep", tree: str = "exact", seed: int = 0, axes: str | Sequence[int] = "cycle") -> DataFrame:
    """Points with the subset they belong to."""
    if partition == "random":
        if labels == "axis":
            raise ValueError("without a tree there is no region to order along an axis")
        return labeling.random_partition(ps.df, subsets, seed)
    if tree == "exact":
        regions = kdtree.build_exact(ps, depth, axes)
    elif tree == "deep":
        regions = kdtree.build_deep(ps, depth, axes)
    else:
        build = {"planes": kdtree.build_planes_exact, "sketch": kdtree.build_planes_sketch, "sampled": kdtree.build_planes_sampled}[tree]
        regions = kdtree.assign_region(ps, build(ps, depth, axes=axes), depth)
    deal = (lambda df: labeling.by_axis(df, label_axis, subsets, ragged)) if labels == "axis" else (lambda df: labeling.by_random(df, seed, subsets, ragged))
    return deal(regions)


def subset_kmeans(ps: PointSet, k: int, init: np.ndarray, *, capacity: int | None = None, subsets: int | None = None, regions: int | None = None, partition: str = "tree", tree: str = "auto", axes: str | Sequence[int] = "cycle", labels: str = "axis", label_axis: int = 0, ragged: str = "proportional", max_subsets: int | None = None, solver: str = "plain", kernel: str = "direct", max_iter: int = 100, tol: float = 0.0, shift: str = "max", empty: str = "keep", asse: str = "sq", how: str = "min_asse", weighted: bool = False, rescore: int = 0, seed: int = 0, n: int | None = None) -> Result:
    """Stratify, solve each subset in one task, merge.

    `tree='auto'` cuts up to AUTO_EXACT points level by level, and beyond that by planes from histograms down to what a task
    holds, and inside the tasks from there on, which are the same cuts. `how` is min_asse, hierarchical, or grouped for any number of candidates."""
    n = ps.count() if n is None else n
    if n < k:
        raise ValueError(f"{n} points cannot give {k} clusters")
    if tree == "auto":
        tree = "exact" if n <= AUTO_EXACT else "deep"
    if tree == "exact" and partition == "tree" and n > kdtree.MOST_EXACT:
        raise ValueError("the level-by-level tree shuffles all points per level: use tree='planes' or 'sampled'")
    depth = kdtree.depth_for(n, capacity, subsets, regions)
    if (1 << depth) < k and partition == "tree" and depth:
        raise ValueError(f"subsets of {1 << depth} points cannot hold {k} distinct centroids")
    m = subsets or max(1, n >> depth)
    held = tree == "deep" and partition == "tree" and not (ps.df.storageLevel.useMemory or ps.df.storageLevel.useDisk)
    if held:  # made once, for the tree and for the subsets
        ps = PointSet(ps.df.persist(), ps.d)
    try:
        lab = labelled(ps, depth, m, partition, labels, label_axis, ragged, tree, seed, axes)
        solved = lab.filter(F.col("label") <= max_subsets) if max_subsets else lab
        cands = subset.solve(solved, init, ps.d, max_iter, tol, solver, asse, empty, kernel=kernel, shift=shift).persist()  # K rows per subset, read by merge and report
        if how == "hierarchical":
            c = merge.hierarchical(cands, k, ps.d, weighted)
        elif how == "grouped":
            c = merge.hierarchical_grouped(cands, k, ps.d)
        elif rescore:
            best = cands.groupBy("subset_id").agg(F.min("asse").alias("asse")).orderBy("asse", "subset_id").limit(rescore).collect()
            tried = [(np.array([[r[x] for x in ps.coords] for r in cands.filter(F.col("subset_id") == b.subset_id).orderBy("cluster_id").collect()]), b.subset_id) for b in best]
            errors = ps.df.agg(*(F.sum(F.floor(assign.nearest([F.col(x) for x in ps.coords], c)["dist2"])).alias(f"e{i}") for i, (c, _) in enumerate(tried))).first()
            c = tried[int(np.argmin(list(errors)))][0]
        else:
            c = merge.min_asse(cands, ps.d, (1 << depth) if ragged == "guard" else 0)
    finally:
        if held:
            ps.df.unpersist()
    return Result(c, cands, lab)


def iterative_kmeans(ps: PointSet, k: int, init: np.ndarray, *, combine: bool = True, how: str = "literal", regions: DataFrame | None = None, max_iter: int = 100, tol: float = 0.0, shift: str = "max") -> Result:
    """One job per round. `combine=False` sends every point to its centroid's reducer, of which there are K at
    most; `combine=True` adds up sums before the shuffle. Centroids are literals, so no round's plan grows."""
    c = np.asarray(init, float).copy()
    result = Result(c)
    boxes = None
    if how == "cells":  # read in every round
        regions = regions.persist()
        boxes = assign.boxes_of(ps, regions).persist()
    for number in range(1, max(1, max_iter) + 1):
        a = {"literal": lambda: assign.by_literal(ps, c), "join": lambda: assign.by_join(ps, c), "arrow": lambda: assign.by_arrow(ps, c), "cells": lambda: assign.by_cells(ps, regions, c, boxes)}[how]()
        if combine:
            rows = a.groupBy("cluster_id").agg(F.count("*").alias("n"), F.sum(F.floor("dist2")).alias("sse"), *(F.sum(x).cast("double").alias(x) for x in ps.coords)).collect()
        else:
            coords = ps.coords

            def mean(batches):
                """Sums by cluster of the points that reached this reducer, batch by batch."""
                import numpy as np
                import pandas as pd

                total: dict[int, list] = {}
                for pdf in batches:
                    for k, part in pdf.groupby("cluster_id"):
                        own = total.setdefault(int(k), [0, 0, *(0.0 for _ in coords)])
                        own[0] += len(part)
                        own[1] += int(np.floor(part.dist2).sum())
                        for i, x in enumerate(coords):
                            own[2 + i] += float(part[x].sum())
                if total:
                    yield pd.DataFrame([(k, *v) for k, v in total.items()], columns=["cluster_id", "n", "sse", *coords])

            dealt = a.select("cluster_id", "dist2", *coords).repartitionById(k, "cluster_id")
            rows = dealt.mapInPandas(mean, "cluster_id int, n long, sse long, " + ", ".join(f"{x} double" for x in coords)).collect()
        new = c.copy()
        for r in rows:
            new[r.cluster_id] = [r[x] / r["n"] for x in ps.coords]
        moved = localsolver.shifted(new, c, shift)
        result.trace.append((number, int(sum(r.sse for r in rows)), moved))
        c = new
        if moved <= tol:
            break
    if how == "cells":
        regions.unpersist()
        boxes.unpersist()
    result.centroids, result.rounds = c, len(result.trace)
    return result


def single_machine(ps: PointSet, k: int, init: np.ndarray, max_iter: int = 100, tol: float = 0.0, most: int = subset.MOST_ROWS, solver: str = "plain") -> Result:
    """All points in one matrix, which one task holds: the yardstick of accuracy, refused for inputs beyond a worker."""
    n = ps.count()
    if n > most:
        raise ValueError(f"{n} points are too many for one machine; the limit is {most}")
    got = subset.solve(ps.df.withColumn("label", F.lit(1).cast("long")), init, ps.d, max_iter, tol, solver, slots=1, most_rows=most).orderBy("cluster_id").collect()
    return Result(np.array([[r[x] for x in ps.coords] for r in got]) if got else np.asarray(init, float), rounds=got[0].rounds if got else 0)


def random_sample_kmeans(ps: PointSet, k: int, init: np.ndarray, share: float, seed: int = 0, **kw) -> Result:
    """Plain random selection of one subset, without strata."""
    n = ps.count()
    return single_machine(PointSet(labeling.prethin(ps.df, n, max(k, int(n * share)), seed), ps.d), k, init, **kw)


def spark_ml(ps: PointSet, k: int, seed: int = 0, max_iter: int = 20) -> Result:
    """Spark's own k-means, an outside check."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.feature import VectorAssembler

    df = VectorAssembler(inputCols=ps.coords, outputCol="features").transform(ps.df)
    return Result(np.array(KMeans(k=k, seed=seed, maxIter=max_iter).fit(df).clusterCenters()))


def sse(ps: PointSet, c: np.ndarray) -> DataFrame:
    """One row: the whole parts of all squared distances, summed."""
    return ps.df.agg(F.sum(F.floor(assign.nearest([F.col(x) for x in ps.coords], c)["dist2"])).alias("sse"))


def grid(ps: PointSet, k: int, init: np.ndarray, depths: Sequence[int], n: int, seed: int = 0, max_iter: int = 30) -> list[tuple]:
    """(partition, labels, merge, subsets, sse) of the six combinations at each depth."""
    rows = []
    for depth in depths:
        for partition, labels in (("tree", "axis"), ("tree", "random"), ("random", "random")):
            lab = labelled(ps, depth, max(1, n >> depth), partition, labels, ragged="proportional", seed=seed)
            cands = subset.solve(lab, init, ps.d, max_iter).persist()
            for how in ("min_asse", "hierarchical"):
                c = merge.min_asse(cands, ps.d) if how == "min_asse" else merge.hierarchical(cands, k, ps.d)
                rows.append((partition, labels, how, n >> depth, int(sse(ps, c).first()[0])))
            cands.unpersist()
    return rows
