"""Sorted groups through Arrow: rows are dealt by key, sorted, and handed on group by group.

A task holds one group at a time, whatever the number of groups of its partition, and a function that keeps
something from group to group sees them in order.
"""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession


def one_thread() -> None:
    """Tasks share a machine's cores already: keep the linear algebra library of this process to one thread."""
    import ctypes
    import glob
    import os

    for path in glob.glob(os.path.join(os.path.dirname(np.__file__) + ".libs", "*openblas*")):
        library = ctypes.CDLL(path)
        for name in ("scipy_openblas_set_num_threads64_", "openblas_set_num_threads64_", "openblas_set_num_threads"):
            if hasattr(library, name):
                getattr(library, name)(1)
                break


def idle_cores(spark: SparkSession, tasks: int) -> int:
    """Cores of an executor for each of so many tasks, if the job has no others: one where the session does not say."""
    sc = spark.sparkContext
    if given := sc.getConf().get("spark.executor.cores"):
        cores = int(given)
    elif cluster := re.fullmatch(r"local-cluster\[\s*\d+\s*,\s*(\d+)\s*,.*", sc.master):
        cores = int(cluster[1])
    else:
        cores = sc.defaultParallelism if sc.master.startswith("local") else 1
    return max(1, cores // max(1, tasks))


def by_group(df: DataFrame, deal: list[str], keys: list[str], order: list[str], make: Callable[[], Callable[[tuple, pa.Table], pa.Table | None]], schema: str) -> DataFrame:
    """deal: columns that rows are partitioned by (all groups of such a key go through one task, in order); keys: the
    columns of a group, deal first; make() gives a fresh function for each task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        one_thread()
        step, held, last = make(), [], None

        def give(key: tuple, parts: list) -> Iterator[pa.RecordBatch]:
            if (made := step(key, pa.Table.from_batches(parts))) is not None:
                yield from made.to_batches()

        for batch in batches:
            if not batch.num_rows:
                continue
            columns = [batch[k] for k in keys]
            changed = np.zeros(batch.num_rows - 1, bool)
            for c in columns:
                empty = c.is_null().to_numpy(zero_copy_only=False)
                v = c.fill_null(c.type.to_pandas_dtype()()).to_numpy(zero_copy_only=False)
                changed |= (v[1:] != v[:-1]) | (empty[1:] != empty[:-1])
            for a, b in zip([0, *(np.flatnonzero(changed) + 1)], [*(np.flatnonzero(changed) + 1), batch.num_rows], strict=True):
                key = tuple(c[int(a)].as_py() for c in columns)
                if held and key != last:
                    yield from give(last, held)
                    held = []
                held.append(batch.slice(int(a), int(b - a)))
                last = key
        if held:
            yield from give(last, held)

    n = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return df.repartition(n, *deal).sortWithinPartitions(*keys, *order).mapInArrow(run, schema)
