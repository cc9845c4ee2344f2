"""Errors over removed cells and what a method costs.

truth: (window_id, inst_id, dim, truth); imputed: chunks or cells. Both errors of all methods run over the same cells,
so the mean magnitude of the cells, error ratio's denominator, must be the same for all; `denominators` shows it.
"""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from streamfill.operators.masks import cells
from streamfill.schema import attributes


def against(truth: DataFrame, imputed: DataFrame) -> DataFrame:
    """Scored cells: truth beside the imputed value."""
    flat = cells(imputed) if attributes(imputed) else imputed
    return truth.join(flat, ["window_id", "inst_id", "dim"])


def _errors():
    gap = F.abs(F.col("truth") - F.col("val"))
    return [F.avg(gap).alias("mae"), F.try_divide(F.sum(gap), F.sum(F.abs("truth"))).alias("mre"), F.count("*").alias("n_cells")]


def pooled(scored: DataFrame, *by: str) -> DataFrame:
    return scored.groupBy(*by).agg(*_errors())


def by_window(scored: DataFrame, *by: str) -> DataFrame:
    return scored.groupBy("window_id", *by).agg(*_errors())


def over_windows(scored: DataFrame, *by: str) -> DataFrame:
    """Errors of each window, then their means over windows."""
    return by_window(scored, *by).groupBy(*by).agg(F.avg("mae").alias("mae"), F.avg("mre").alias("mre"), F.sum("n_cells").alias("n_cells"), F.count("*").alias("n_windows"))


def rolled(scored: DataFrame, *by: str) -> DataFrame:
    return scored.rollup(*by).agg(*_errors())


def cubed(scored: DataFrame, *by: str) -> DataFrame:
    return scored.cube(*by).agg(*_errors())


def grouped_by_sets(scored: DataFrame, *sets: tuple[str, ...]) -> DataFrame:
    """Errors of several groupings at once, each a tuple of columns."""
    columns = sorted({c for s in sets for c in s})
    return scored.groupingSets([[F.col(c) for c in s] for s in sets], *columns).agg(*_errors())


def resume_gain(scratch: DataFrame, resumed: DataFrame) -> DataFrame:
    """What starting from the last window's weights saves, by window: seconds and epochs to the best of both, and the
    differences. Both come from the same chunks, with seconds and best epochs as the engine reports them."""
    cost = lambda df, name: df.groupBy("window_id").agg(F.max("total_s").alias(f"{name}_s"), F.max("best_epoch").alias(f"{name}_epoch"))
    both = cost(scratch, "scratch").join(cost(resumed, "resumed"), "window_id")
    return both.withColumns({"gain_s": F.col("scratch_s") - F.col("resumed_s"), "gain_epochs": F.col("scratch_epoch") - F.col("resumed_epoch")})


def denominators(scored: DataFrame, method: str = "method") -> DataFrame:
    return scored.groupBy(method).agg(F.avg(F.abs("truth")).alias("magnitude"), F.count("*").alias("n_cells"))


def sparsity(df: DataFrame) -> DataFrame:
    xs = attributes(df)
    seen = sum((F.count(c) for c in xs), F.lit(0))
    return df.agg(F.count("*").alias("n"), (F.count("*") * len(xs) - seen).alias("missing"), (1 - seen / (F.count("*") * len(xs))).alias("sparsity"))


def cache_rows(cached: DataFrame) -> DataFrame:
    return cached.groupBy("window_id").agg(F.count("*").alias("rows"))


def timed(run: Callable[[], DataFrame]) -> tuple[float, int]:
    """(seconds, rows) of carrying a plan out whole."""
    began = time.perf_counter()
    n = run().count()
    return time.perf_counter() - began, n
