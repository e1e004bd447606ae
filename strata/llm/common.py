"""What the text operators share: reading, worker-side caches, checkpoints, spans."""

from __future__ import annotations

import gc
import sys
import types
from collections.abc import Callable, Iterator

import pyspark.cloudpickle as cloudpickle
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

import strata

# Kernels travel by value, so executors need not have this package on their path.
cloudpickle.register_pickle_by_value(strata)


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def give_back() -> None:
    """Returns freed memory of this process to the system: allocators keep it otherwise, and a worker lives on."""
    import ctypes

    import pyarrow as pa

    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


def worker_cache(user: str, key: str, make: Callable, instead_of: str | None = None):
    """An object that lives as long as the Python worker and serves its later tasks too.

    A worker keeps the objects of one `user`, an operator, at a time: the first call of another drops them, so stages
    of a pipeline do not add up in memory. With `instead_of`, the name of a purpose, the object replaces what was
    kept for that purpose under another key.
    """
    store = sys.modules.setdefault("_strata_worker_cache", types.ModuleType("_strata_worker_cache")).__dict__
    if store.get("user") != user:
        store["user"], store["kept"], store["purposes"] = user, {}, {}
        give_back()
    kept, purposes = store["kept"], store["purposes"]
    if instead_of and purposes.get(instead_of) != key:
        kept.pop(purposes.get(instead_of), None)
        purposes[instead_of] = key
    if key not in kept:
        kept[key] = make()
    return kept[key]


def materialize(df: DataFrame) -> DataFrame:
    """Cut the lineage with a copy in the shared checkpoint folder, which outlives executors.

    The folder is the session's `spark.checkpoint.dir`; only where a session names none
    (tests on one machine) is one chosen here.
    """
    sc = df.sparkSession.sparkContext
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        sc.setCheckpointDir(sc.getConf().get("spark.checkpoint.dir") or "/tmp/checkpoints")
    return df.checkpoint(eager=True)


def release(spark: SparkSession) -> None:
    """Has the driver collect its garbage: shuffle files of what is no longer used stay on executors' disks until it does,
    which on a driver with little else to do can be long after they have become the larger part."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def map_texts(df: DataFrame, columns: list[str], kernel: Callable[[Iterator[dict]], Iterator[dict]], schema: str) -> DataFrame:
    """`kernel` gets the named columns of each Arrow batch as lists, and returns columns of `schema`.

    Rows are cut into slices of bounded text, so a batch of very long documents
    does not have to fit a worker at once.
    """
    from pyspark.sql.types import _parse_datatype_string
    from pyspark.sql.pandas.types import to_arrow_schema

    out = to_arrow_schema(_parse_datatype_string(schema))

    def run(batches):
        import pyarrow as pa

        def values(column):
            """A list; of numpy arrays where the column holds lists of integers."""
            if not (pa.types.is_list(column.type) and pa.types.is_integer(column.type.value_type)):
                return column.to_pylist()
            ends, flat = column.offsets.to_pylist(), column.values.to_numpy(zero_copy_only=False)
            return [None if null else flat[a:b] for a, b, null in zip(ends, ends[1:], column.is_null().to_pylist())]

        def slices():
            for batch in batches:
                step = max(1, min(batch.num_rows, int(batch.num_rows * 8e6 / max(1, batch.nbytes)) + 1))
                for at in range(0, batch.num_rows, step):
                    part = batch.slice(at, step)
                    yield {c: values(part.column(k)) for k, c in enumerate(columns)}

        for result in kernel(slices()):
            yield pa.RecordBatch.from_arrays([x.cast(f.type) if isinstance(x := result[f.name], pa.Array) else pa.array(x, f.type) for f in out], schema=out)

    return df.select(*columns).mapInArrow(run, schema)


def sha_hex(col: Column) -> Column:
    return F.sha2(col.cast("binary"), 256)
