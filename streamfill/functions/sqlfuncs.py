"""Functions for SQL text: masks, overlap, errors, cells, neighbours, whole windows."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import Row

from streamfill.functions import kernels


class ExplodeCells:
    """A row's array of attributes as rows (dim, val)."""

    def eval(self, x: list):
        for d, v in enumerate(x or []):
            yield d, v


class NeighbourBlock:
    """TABLE argument (inst_id, x array, k) partitioned by window: rows (src, dst) of the nearest neighbours. Holds one partition."""

    def __init__(self) -> None:
        self.ids, self.rows, self.k = [], [], 10

    def eval(self, row: Row):
        self.ids.append(row["inst_id"])
        self.rows.append([np.nan if v is None else v for v in row["x"]])
        self.k = row["k"]

    def terminate(self):
        order = np.argsort(self.ids)
        x = kernels.mean_filled(np.array(self.rows, float)[order])
        for i, near in enumerate(kernels.nearest(x, self.k)):
            for j in near:
                yield self.ids[order[i]], self.ids[order[j]]


def register(spark: SparkSession) -> None:
    """or_count(x), oor(x, y), is_missing(x) as SQL expressions; mae, mre and euclid in Arrow batches; explode_cells and knn_block as table functions."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION or_count(x ARRAY<DOUBLE>) RETURNS INT RETURN size(filter(x, v -> v IS NOT NULL))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION oor(x ARRAY<DOUBLE>, y ARRAY<DOUBLE>) RETURNS INT RETURN size(filter(zip_with(x, y, (a, b) -> a IS NOT NULL AND b IS NOT NULL), v -> v))")

    @F.pandas_udf("double")
    def mae(truth: pd.Series, val: pd.Series) -> float:
        return float((truth - val).abs().mean())

    @F.pandas_udf("double")
    def mre(truth: pd.Series, val: pd.Series) -> float | None:
        size = truth.abs().sum()
        return float((truth - val).abs().sum() / size) if size else None

    @F.pandas_udf("double")
    def euclid(pairs: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
        for a, b in pairs:
            yield pd.Series([float(np.linalg.norm(np.asarray(p) - np.asarray(q))) if p is not None and q is not None else None for p, q in zip(a, b, strict=True)], dtype="float64")

    for name, f in (("mae", mae), ("mre", mre), ("euclid", euclid)):
        spark.udf.register(name, f)
    spark.udtf.register("explode_cells", F.udtf(ExplodeCells, returnType="dim int, val double"))
    spark.udtf.register("knn_block", F.udtf(NeighbourBlock, returnType="src long, dst long"))
