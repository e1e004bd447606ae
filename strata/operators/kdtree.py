"""k-d trees by median cuts: regions as heap codes (root 1, children 2r and 2r+1).

A cut is the point of rank ceil(n/2) of its region in the order (coordinate, point_id);
points up to it go left. Depth comes from the counts alone, so no level is counted.
"""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from strata.functions.points import PointSet

#: Rows up to which the level-by-level tree, which shuffles points, is allowed.
MOST_EXACT = 10_000_000


def depth_for(n: int, capacity: int | None = None, subsets: int | None = None, regions: int | None = None) -> int:
    given = [x for x in (capacity, subsets, regions) if x is not None]
    if len(given) != 1:
        raise ValueError("give one of capacity, subsets and regions")
    if n <= 0:
        raise ValueError(f"no points to cut (n = {n})")
    if capacity is not None:
        return max(0, math.ceil(math.log2(n / capacity)))
    if subsets is not None:
        return max(0, math.floor(math.log2(n / subsets))) if n >= subsets else 0
    return int(regions).bit_length() - 1


def axis_of(level: int, d: int, axes: str | Sequence[int] = "cycle") -> int:
    return level % d if axes == "cycle" else axes[level % len(axes)]


def widest(low: Sequence, high: Sequence) -> int:
    """The axis of the largest extent, the first among equals."""
    return max(range(len(low)), key=lambda k: (high[k] - low[k], -k))


def build_exact(ps: PointSet, depth: int, axes: str | Sequence[int] = "cycle", partitions: int | None = None) -> DataFrame:
    """Points with region_id, one exchange per level. The first level is a single region, hence one task:
    use `build_planes_exact` or `build_planes_sampled` on large inputs. `axes` is 'cycle', 'widest' or a list."""
    df = ps.df.withColumn("region_id", F.lit(1).cast("long"))
    for level in range(depth):
        # the explicit exchange keeps a constant first key from holding all later levels in one task
        df = df.repartition(*((partitions,) if partitions else ()), "region_id")
        w = Window.partitionBy("region_id")
        if axes == "widest":
            extents = [F.struct((F.max(c).over(w) - F.min(c).over(w)).alias("e"), F.lit(-k).alias("k")) for k, c in enumerate(ps.coords)]
            df = df.withColumn("_axis", F.greatest(*extents)["k"] if len(extents) > 1 else F.lit(0))
            df = df.withColumn("_cut", F.coalesce(*(F.when(F.col("_axis") == -k, F.col(c)) for k, c in enumerate(ps.coords))))
            order = w.orderBy("_cut", "point_id")
        else:
            order = w.orderBy(f"c{axis_of(level, ps.d, axes)}", "point_id")
        # the first of two tiles has the odd row, as a cut at rank ceil(n / 2) does
        df = df.withColumn("_tile", F.ntile(2).over(order)).withColumn("region_id", (F.col("region_id") * 2 + F.col("_tile") - 1).cast("long")).drop("_tile", "_axis", "_cut")
    return df


def assign_region(ps: PointSet, planes: DataFrame, depth: int) -> DataFrame:
    """Walks the planes, whose number is bounded by 2^depth, level by level as broadcast lookups. A region without a
    plane is a leaf whose points go left."""
    df = ps.df.withColumn("region_id", F.lit(1).cast("long"))
    for level in range(depth):
        own = planes.filter((F.col("node") >= 1 << level) & (F.col("node") < 2 << level)).select(F.col("node").alias("region_id"), "axis", "cut_value", "cut_id")
        c = F.coalesce(*(F.when(F.col("axis") == k, F.col(x)) for k, x in enumerate(ps.coords)))
        right = (c > F.col("cut_value")) | ((c == F.col("cut_value")) & (F.col("point_id") > F.col("cut_id")))
        df = df.join(F.broadcast(own), "region_id", "left").withColumn("region_id", F.col("region_id") * 2 + F.coalesce(right, F.lit(False)).cast("long")).drop("axis", "cut_value", "cut_id")
    return df


def build_planes_exact(ps: PointSet, depth: int, axes: str | Sequence[int] = "cycle", bins: int = 1024) -> DataFrame:
    """(node, axis, cut_value, cut_id), by rank targets located in histograms; points are never shuffled.

    A level costs a few scans: each narrows the value range of every region's median by
    `bins`, until the range is one value; the id is then found the same way. What moves
    is bounded by regions times bins.
    """
    spark = ps.df.sparkSession
    planes = None
    schema = "node long, axis int, cut_value long, cut_id long"
    for level in range(depth):
        regions = assign_region(ps, planes, level) if level else ps.df.withColumn("region_id", F.lit(1).cast("long"))
        found = regions.groupBy("region_id").agg(F.count("*").alias("n"), *(f(F.col(c).cast("long")).alias(f"{name}{k}") for k, c in enumerate(ps.coords) for name, f in (("lo", F.min), ("hi", F.max)))).collect()
        if axes == "widest":
            axis = {r.region_id: widest(*([r[f"{x}{k}"] for k in range(ps.d)] for x in ("lo", "hi"))) for r in found}
        else:
            axis = {r.region_id: axis_of(level, ps.d, axes) for r in found}
        ends = {r.region_id: [(r.n + 1) // 2, r[f"lo{axis[r.region_id]}"], r[f"hi{axis[r.region_id]}"]] for r in found}
        if len(set(axis.values())) == 1:
            v = F.col(f"c{next(iter(axis.values()))}").cast("long")
        else:
            chosen = F.broadcast(spark.createDataFrame(list(axis.items()), "region_id long, _axis int"))  # one row per region
            regions = regions.join(chosen, "region_id")
            v = F.coalesce(*(F.when(F.col("_axis") == k, F.col(c)) for k, c in enumerate(ps.coords))).cast("long")
        values = _select(spark, regions.select("region_id", v.alias("v")), ends, bins)
        at = spark.createDataFrame([(g, x) for g, (x, _) in values.items()], "region_id long, value long")
        tied = regions.select("region_id", v.alias("value"), F.col("point_id").alias("v")).join(F.broadcast(at), ["region_id", "value"])
        ids = {r.region_id: [values[r.region_id][1], r.lo, r.hi] for r in tied.groupBy("region_id").agg(F.min("v").alias("lo"), F.max("v").alias("hi")).collect()}
        chosen_ids = _select(spark, tied.select("region_id", "v"), ids, bins)
        rows = [(int(g), axis[g], int(values[g][0]), int(chosen_ids[g][0])) for g in values]
        new = spark.createDataFrame(rows, schema)
        planes = new if planes is None else planes.union(new)
    return planes if planes is not None else spark.createDataFrame([], schema)


#: Points of the sample that says where to look for medians, and rows that are looked through on the driver at once.
SAMPLE, LOOKED_THROUGH = 1 << 16, 100_000


def _of_region(values, level: int) -> Column:
    """The own value of a row's region, out of an array, which is a literal, of a value for each region of the level."""
    import numpy as np

    return F.get(F.lit(np.asarray(values)), (F.col("region_id") - F.lit(1 << level)).cast("int"))


def _coordinate(ps: PointSet, axis, level: int) -> Column:
    """The coordinate that a row's region is cut along."""
    if len(set(axis.tolist())) == 1:
        return F.col(f"c{axis[0]}")
    return F.coalesce(*(F.when(_of_region(axis, level) == k, F.col(c)) for k, c in enumerate(ps.coords)))


def _walked(ps: PointSet, cuts: list[tuple]) -> DataFrame:
    """Points with region_id, by the (axis, value, id) of all regions of each level as literals: no join."""
    df = ps.df.withColumn("region_id", F.lit(1).cast("long"))
    for level, (axis, value, last) in enumerate(cuts):
        c, cut = _coordinate(ps, axis, level), _of_region(value, level)
        right = (c > cut) | ((c == cut) & (F.col("point_id") > _of_region(last, level)))
        df = df.withColumn("region_id", F.col("region_id") * 2 + right.cast("long"))
    return df


def _nth(rows: DataFrame, level: int, low, high, rank=None, of_ids: bool = False, bins: int = 256) -> tuple:
    """The (v, point_id) of each region's row of the rank in that order, or of its middle row where no rank is given. Any range from
    `low` to `high` gives the same answer: the rows of a bin and those on either side are counted with their least and largest
    value, so each job narrows the range to the rows of one bin, until a few are left for the driver to sort. Ranks that are given
    count the rows inside the range. Rows are picked by aggregates: a filter would be pushed below the walk and repeat it."""
    import numpy as np

    low, high, many = low.copy(), high.copy(), len(low)
    within = rank is not None
    rank = rank.copy() if within else np.zeros(many, "int64")
    ids, v = np.zeros((2, many), "int64"), F.col("v")
    while True:
        wide = max(b - a for a, b in zip(low.tolist(), high.tolist())) > 1 << 62  # then a difference of long numbers may overflow
        step = (high.astype(float) - low.astype(float) if wide else high - low) / bins
        lo, hi, width = _of_region(low, level), _of_region(high, level), _of_region(np.where(step > 0, step, 1.0), level)
        bin_ = F.when(v.isNull() | (v < lo), -1).when(v > hi, bins).otherwise(F.least(F.lit(bins - 1), F.floor(((v.cast("double") if wide else v) - lo) / width)))
        counts = rows.groupBy("region_id", bin_.cast("int").alias("bin")).agg(F.count("*").alias("n"), F.min("v").alias("lo"), F.max("v").alias("hi"), F.min("point_id").alias("from"), F.max("point_id").alias("to")).collect()
        found: dict[int, list] = {}
        for r in sorted(counts, key=lambda r: (r.region_id, r.bin)):
            if not within or 0 <= r.bin < bins:
                found.setdefault(r.region_id - many, []).append(r)
        total = 0
        for g, own in found.items():
            k = int(rank[g]) if within else (sum(r.n for r in own) + 1) // 2
            for r in own:
                if k <= r.n:
                    break
                k -= r.n
            rank[g], low[g], high[g], ids[:, g] = k, r.lo, r.hi, (r["from"], r.to)
            total += r.n
        within = True
        lo, hi = _of_region(low, level), _of_region(high, level)
        if total <= LOOKED_THROUGH:
            value, last = low.copy(), np.zeros(many, "int64")
            left = rows.groupBy("region_id").agg(F.collect_list(F.when(v.between(lo, hi), F.struct("v", "point_id"))).alias("rows")).toArrow()
            for region, own in zip(left["region_id"].to_pylist(), left["rows"]):
                if region - many in found:
                    x, i = (own.values.field(name).to_numpy() for name in ("v", "point_id"))
                    at = np.lexsort((i, x))[rank[region - many] - 1]
                    value[region - many], last[region - many] = x[at], i[at]
            return value, last
        if (low == high).all():  # equal values, in the order of their ids
            return (low, low) if of_ids else (low, _nth(rows.withColumn("v", F.when(v == lo, F.col("point_id").cast("long"))), level, *ids, rank, True, bins)[1])


def _cuts(ps: PointSet, n: int, levels: int, axes: str | Sequence[int] = "cycle") -> list[tuple]:
    """For each of the first levels the axis, value and id that all its regions are cut at, the same as `build_exact`. A sample on the
    driver says in which range a median lies, so that a level takes a count of that range and the rows of a bin of it."""
    import numpy as np

    share = int(math.ceil(min(1.0, SAMPLE / max(1, n)) * 1_000_003))
    sample = ps.df.filter(F.pmod(F.xxhash64("point_id"), F.lit(1_000_003)) < share).select("point_id", *ps.coords).toArrow()
    own, x = sample["point_id"].to_numpy(), [sample[c].to_numpy() for c in ps.coords]
    kind = "int64" if all(a.dtype.kind in "iu" for a in x) else "float64"
    x = [a.astype(kind) for a in x]
    region, cuts = np.zeros(len(own), "int64"), []
    for level in range(levels):
        many, rows = 1 << level, _walked(ps, cuts)
        axis = np.full(many, 0 if axes == "widest" else axis_of(level, ps.d, axes), "int32")
        if axes == "widest":
            for r in rows.groupBy("region_id").agg(*(f(c).alias(f"{name}{k}") for k, c in enumerate(ps.coords) for name, f in (("lo", F.min), ("hi", F.max)))).collect():
                axis[r.region_id - many] = widest(*([r[f"{x}{k}"] for k in range(ps.d)] for x in ("lo", "hi")))
        v = np.choose(axis[region], x)
        order = np.lexsort((v, region))
        begins = np.searchsorted(region[order], np.arange(many + 1))
        low, high = np.zeros(many, kind), np.zeros(many, kind)
        for g, (a, b) in enumerate(zip(begins, begins[1:])):
            if a < b:
                aside = 2 + int(3 * math.sqrt(b - a))  # six deviations of a sample's median
                low[g], high[g] = v[order[max(a, (a + b) // 2 - aside)]], v[order[min(b - 1, (a + b) // 2 + aside)]]
        value, last = _nth(rows.select("region_id", _coordinate(ps, axis, level).alias("v"), "point_id"), level, low, high)
        cuts.append((axis, value, last))
        region = 2 * region + ((v > value[region]) | ((v == value[region]) & (own > last[region])))
    return cuts


def build_deep(ps: PointSet, depth: int, axes: str | Sequence[int] = "cycle", per_task: int = 1 << 18) -> DataFrame:
    """Points with region_id, the same as `build_exact` gives, for many points and any depth: cuts found by counting give the top
    levels, until a region is about `per_task` points; all levels below are cut in memory by a task per region, after one shuffle."""
    n = ps.count()
    top = min(depth, (n // per_task).bit_length())
    regions = ps.df.withColumn("region_id", F.lit(1).cast("long"))
    if top:
        own = not (ps.df.storageLevel.useMemory or ps.df.storageLevel.useDisk)
        held = PointSet(ps.df.persist(), ps.d) if own else ps  # read twice a level
        regions = _walked(ps, _cuts(held, n, top, axes))
        if own:
            held.df.unpersist()
    coords, schema = list(ps.coords), regions.schema

    def lower(group):
        import numpy as np
        import pandas as pd

        region, ids, x = group.region_id.to_numpy("int64").copy(), group.point_id.to_numpy(), [group[c].to_numpy() for c in coords]
        for level in range(top, depth):
            if axes == "widest":
                by = pd.DataFrame(dict(enumerate(x))).groupby(region)
                axis = pd.Series((by.max() - by.min()).to_numpy().argmax(1), by.size().index).reindex(region).to_numpy()
                v = np.choose(axis, x)
            else:
                v = x[axis_of(level, len(coords), axes)]
            order = np.lexsort((ids, v, region))
            own = region[order]
            first = np.flatnonzero(np.r_[True, own[1:] != own[:-1]])
            sizes = np.diff(np.r_[first, len(own)])
            rank = np.arange(len(own)) - np.repeat(first, sizes)
            region[order] = 2 * own + (rank >= np.repeat((sizes + 1) // 2, sizes))
        return group.assign(region_id=region)

    return regions.groupBy("region_id").applyInPandas(lower, schema) if top < depth else regions


def _select(spark, rows: DataFrame, ranges: dict, bins: int) -> dict:
    """For each region, the value of the wanted rank among its rows' v, and the rank left within equal values."""
    ranges = {g: list(x) for g, x in ranges.items()}
    while any(lo < hi for _, lo, hi in ranges.values()):
        open_ = [(g, lo, hi, max(1, -(-(hi - lo + 1) // bins))) for g, (_, lo, hi) in ranges.items() if lo < hi]
        limits = F.broadcast(spark.createDataFrame(open_, "region_id long, lo long, hi long, step long"))
        hist = rows.join(limits, "region_id").filter("v between lo and hi").groupBy("region_id", F.floor((F.col("v") - F.col("lo")) / F.col("step")).alias("bin")).count().collect()
        sums: dict = {}
        for r in hist:
            sums.setdefault(r.region_id, {})[r.bin] = r["count"]
        for g, lo, hi, step in open_:
            k = ranges[g][0]
            for b in sorted(sums[g]):
                if k <= sums[g][b]:
                    break
                k -= sums[g][b]
            ranges[g] = [k, lo + b * step, min(hi, lo + (b + 1) * step - 1)]
    return {g: (lo, k) for g, (k, lo, _) in ranges.items()}


def build_planes_sketch(ps: PointSet, depth: int, accuracy: int = 10_000, axes: str | Sequence[int] = "cycle") -> DataFrame:
    """Planes from mergeable quantile sketches: one scan per level, leaves even within about 1/accuracy a level."""
    spark, planes = ps.df.sparkSession, None
    schema = "node long, axis int, cut_value long, cut_id long"
    for level in range(depth):
        axis = axis_of(level, ps.d, axes)
        regions = assign_region(ps, planes, level) if level else ps.df.withColumn("region_id", F.lit(1).cast("long"))
        got = regions.groupBy("region_id").agg(F.percentile_approx(f"c{axis}", 0.5, accuracy).alias("v")).collect()
        new = spark.createDataFrame([(r.region_id, axis, int(r.v), 2**62) for r in got], schema)
        planes = new if planes is None else planes.union(new)
    return planes if planes is not None else spark.createDataFrame([], schema)


def cut_sample(sample, coords: Sequence[str], levels: int, first_level: int = 0, root: int = 1, axes: str | Sequence[int] = "cycle") -> list[tuple]:
    """Planes (node, axis, cut_value, cut_id) of a pandas frame of points, from `root` on, which lies at `first_level`."""
    import numpy as np

    rows, parts = [], {root: sample}
    for level in range(first_level, first_level + levels):
        below = {}
        for node, part in parts.items():
            if part.empty:
                continue
            axis = widest(part[coords].min().tolist(), part[coords].max().tolist()) if axes == "widest" else axis_of(level, len(coords), axes)
            order = np.lexsort((part.point_id.to_numpy(), part[coords[axis]].to_numpy()))
            cut = (len(order) + 1) // 2
            row = part.iloc[order[cut - 1]]
            rows.append((node, axis, int(row[coords[axis]]), int(row.point_id)))
            below[2 * node], below[2 * node + 1] = part.iloc[order[:cut]], part.iloc[order[cut:]]
        parts = below
    return rows


def build_planes_sampled(ps: PointSet, depth: int, per_leaf: int = 256, seed: int = 0, axes: str | Sequence[int] = "cycle", on_driver: int = 1 << 16) -> DataFrame:
    """Planes of a hash sample of `per_leaf` points per region. The top levels, as many as a sample of `on_driver` points
    serves, are cut on the driver; the levels below by one task for each of their regions, from its own points."""
    spark, coords, schema = ps.df.sparkSession, list(ps.coords), "node long, axis int, cut_value long, cut_id long"
    n = max(1, ps.count())
    top = min(depth, max(1, (on_driver // per_leaf).bit_length() - 1))

    def sampled(levels):
        share = min(1.0, (per_leaf << levels) / n)
        return ps.df.filter(F.pmod(F.xxhash64("point_id", F.lit(seed)), F.lit(1_000_003)) < int(math.ceil(share * 1_000_003))).select("point_id", *coords)

    planes = spark.createDataFrame(cut_sample(sampled(top).toPandas(), coords, top, axes=axes), schema)
    if top == depth:
        return planes

    def lower(group):
        import pandas as pd

        rows = cut_sample(group, coords, depth - top, top, int(group.region_id.iloc[0]), axes)
        return pd.DataFrame(rows, columns=["node", "axis", "cut_value", "cut_id"])

    below = assign_region(PointSet(sampled(depth), ps.d), planes, top)
    rows = below.groupBy("region_id").applyInPandas(lower, schema).collect()  # under 2^depth rows
    return planes.union(spark.createDataFrame(rows, schema))


def bit_path(region_id: Column) -> Column:
    """The way from the root as zeros and ones."""
    return F.substring(F.bin(region_id), 2, 64)


def range_regions(planes: DataFrame, depth: int, box: dict[int, tuple[int, int]]) -> list[int]:
    """Regions that a box can meet, by descending the planes on the driver."""
    by = {r.node: r for r in planes.collect()}
    nodes = [1]
    for _ in range(depth):
        below = []
        for node in nodes:
            p = by.get(node)
            lo, hi = box.get(p.axis, (-math.inf, math.inf)) if p else (-math.inf, math.inf)
            if p is None or lo <= p.cut_value:
                below.append(2 * node)
            if p is None or hi >= p.cut_value:
                below.append(2 * node + 1)
        nodes = below
    return nodes
