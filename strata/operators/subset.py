"""Every subset solved to convergence inside one task, after one shuffle."""

from __future__ import annotations

import numpy as np
import pyspark.cloudpickle as cloudpickle
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

import strata
from strata.operators import localsolver

cloudpickle.register_pickle_by_value(strata)


def candidate_schema(d: int) -> str:
    return "subset_id long, cluster_id int, " + ", ".join(f"c{k} double" for k in range(d)) + ", members long, sse long, asse double, rounds int, converged boolean"


#: Rows of whole subsets that are solved together, and rows of one subset beyond which the settings are refused.
TOGETHER, MOST_ROWS = 100_000, 50_000_000


def solve(labelled: DataFrame, init: np.ndarray, d: int, max_iter: int | None = 100, tol: float = 0.0, solver: str = "plain", asse: str = "sq", empty: str = "keep", slots: int | None = None, kernel: str = "direct", shift: str = "max", most_rows: int = MOST_ROWS) -> DataFrame:
    """(subset_id, cluster_id, c*, members, sse, asse, rounds, converged): K rows per subset.

    Subsets are dealt to partitions by number, not by hash, so none sits idle while another holds several; a
    partition's rows arrive in the order of subsets, and small subsets are solved many at a time. `asse` is the mean
    squared distance (`sq`, from the whole part of each, so that it adds up exactly) or the mean distance (`dist`).
    A subset of over `most_rows` rows stops the query: it asks for more subsets, or for `max_subsets` of them.
    """
    spark = labelled.sparkSession
    slots = slots or 3 * spark.sparkContext.defaultParallelism
    init, coords = np.asarray(init, float), [f"c{k}" for k in range(d)]
    schema = candidate_schema(d)

    def solved(x, first):
        """(centroids, labels, d2, rounds, converged) of the matrices that begin at `first`."""
        if solver == "plain" and kernel == "direct" and len(first) > 1:
            return localsolver.solve_many(x, first, init, max_iter, tol, empty, shift)
        each = [localsolver.solve(part, init, max_iter, tol, solver, kernel, empty, shift) for part in np.split(x, first[1:])]
        return np.stack([s.centroids for s in each]), np.concatenate([s.labels for s in each]), np.concatenate([s.d2 for s in each]), np.array([s.rounds for s in each]), np.array([s.converged for s in each])

    def answer(x, labels):
        import pandas as pd

        first = np.flatnonzero(np.r_[True, labels[1:] != labels[:-1]])
        c, cluster, d2, rounds, converged = solved(x, first)
        many, k = len(first), len(init)
        owner = np.repeat(np.arange(many), np.diff(np.r_[first, len(x)]))
        cell = owner * k + cluster
        members = np.bincount(cell, minlength=many * k)
        sse = np.bincount(cell, np.floor(d2), many * k).astype("int64")
        n = np.diff(np.r_[first, len(x)])
        error = sse.reshape(many, k).sum(1).astype(float) / n if asse == "sq" else np.array([float(np.sqrt(p).sum()) for p in np.split(d2, first[1:])]) / n
        out = {"subset_id": np.repeat(labels[first], k), "cluster_id": np.tile(np.arange(k), many), **{name: c[..., a].ravel() for a, name in enumerate(coords)}}
        return pd.DataFrame(out | {"members": members, "sse": sse, "asse": np.repeat(error, k), "rounds": np.repeat(rounds, k), "converged": np.repeat(converged, k)})

    def run(batches):
        held_x, held_labels, held = [], [], 0
        for pdf in batches:
            if not len(pdf):
                continue
            held_x.append(pdf[coords].to_numpy(float))
            held_labels.append(pdf["label"].to_numpy("int64"))
            held += len(pdf)
            last = held_labels[-1][-1]
            if held >= TOGETHER and held_labels[0][0] != last:  # rows of one subset are put together once, at its end
                x, labels = np.concatenate(held_x), np.concatenate(held_labels)
                cut = int(np.searchsorted(labels, last))  # the last subset may go on in the next batch
                yield answer(x[:cut], labels[:cut])
                held_x, held_labels, held = [x[cut:]], [labels[cut:]], len(x) - cut
            if held > most_rows and held_labels[0][0] == last:
                raise ValueError(f"subset {last} has over {most_rows} rows: ask for more subsets")
        if held:
            yield answer(np.concatenate(held_x), np.concatenate(held_labels))

    dealt = labelled.select("point_id", *coords, "label", F.pmod("label", F.lit(slots)).cast("int").alias("slot")).repartitionById(slots, "slot")
    return dealt.sortWithinPartitions("label", "point_id").select(*coords, "label").mapInPandas(run, schema)
