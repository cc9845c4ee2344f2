"""Regression and low-rank imputers at any number of rows: what they need of the rows is the Gramian, one aggregation of
D * D numbers a window; what is solved from it is a small matrix a window, and applying it is a narrow step.

Both agree with the kernels that hold a window's rows (see the tests); windows are keys here, so a window may be as
large as the table.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from streamfill.operators.fill import mean_fill, means
from streamfill.schema import attributes
from streamfill.sources.durable import settle


def gramian(df: DataFrame, where: str | None = None) -> DataFrame:
    """(window_id, n, g): sums of products of (1, x0, x1, ...) by window, the upper triangle row by row, over the rows
    where a condition holds."""
    one = [F.lit(1.0), *(F.col(c) for c in attributes(df))]
    kept = df.where(where) if where else df
    products = [F.sum(one[i] * one[j]) for i in range(len(one)) for j in range(i, len(one))]
    return kept.groupBy("window_id").agg(F.count("*").alias("n"), F.array(*products).alias("g"))


def _square(flat: np.ndarray, size: int) -> np.ndarray:
    out = np.zeros((size, size))
    out[np.triu_indices(size)] = flat
    return out + np.triu(out, 1).T


def _solved(grams: DataFrame, size: int, solve) -> DataFrame:
    """(window_id, w): solve(matrix, n) of each window, flattened."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            made = [solve(_square(np.array(g), size), n).ravel().tolist() for g, n in zip(batch["g"].to_pylist(), batch["n"].to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([batch["window_id"], pa.array(made, pa.list_(pa.float64()))], names=["window_id", "w"])

    return grams.select("window_id", "n", "g").mapInArrow(run, "window_id long, w array<double>")


def mice(df: DataFrame, rounds: int = 5, ridge: float = 1e-2) -> DataFrame:
    """Round-robin ridge regressions, each from one aggregation: for every attribute, the Gramian of the rows that
    observe it, a solution a window, and predictions for the rows that do not, which are settled."""
    xs = attributes(df)
    size = len(xs) + 1
    gone = [F.col(c).isNull().alias(f"g{c[1:]}") for c in xs]
    flags = df.select("window_id", "stream_id", "inst_id", *(F.col(c) for c in xs), F.array(*gone).alias("gone"))
    us = means(df)
    now = flags.join(us, "window_id").select("window_id", "stream_id", "inst_id", *(F.coalesce(c, f"u{c[1:]}").alias(c) for c in xs), "gone")
    now = settle(now)
    for _ in range(rounds):
        for j in range(len(xs)):
            others = [0, *(k + 1 for k in range(len(xs)) if k != j)]

            def solve(m: np.ndarray, n: int, j: int = j, others: list[int] = others) -> np.ndarray:
                if n < 2:
                    return np.zeros(0)
                left = m[np.ix_(others, others)] + ridge * n * np.diag([0.0, *np.ones(len(others) - 1)])
                return np.linalg.lstsq(left, m[others, j + 1], rcond=None)[0]

            beta = _solved(gramian(now.where(~F.get("gone", F.lit(j)))), size, solve)
            terms = [F.get("w", F.lit(0)), *(F.get("w", F.lit(at)) * F.col(xs[k - 1]) for at, k in enumerate(others) if k)]
            guess = sum(terms[1:], terms[0])
            now = now.join(beta, "window_id", "left").withColumn(xs[j], F.when(F.get("gone", F.lit(j)), F.coalesce(guess, F.col(xs[j]))).otherwise(F.col(xs[j])))
            now = settle(now.select("window_id", "stream_id", "inst_id", *xs, "gone"))  # it is read twice by the next
    return now.drop("gone")


def mf(df: DataFrame, rank: int | None = None, iters: int = 20) -> DataFrame:
    """Repeated projection on the leading directions of the Gramian; every step is settled, as the next reads it twice."""
    xs = attributes(df)
    rank = min(rank or min(8, len(xs)), len(xs))
    size = len(xs) + 1
    now = mean_fill(df)
    flags = df.select("window_id", "inst_id", F.array(*(F.col(c).isNull() for c in xs)).alias("gone"))
    now = settle(now.join(flags, ["window_id", "inst_id"]))

    def directions(m: np.ndarray, n: int) -> np.ndarray:
        v = np.linalg.eigh(m[1:, 1:])[1][:, -rank:]
        return v @ v.T

    for _ in range(iters):
        made = now.join(_solved(gramian(now), size, directions), "window_id")
        cell = lambda d: sum((F.col(c) * F.get("w", F.lit(k * len(xs) + d)) for k, c in enumerate(xs)), F.lit(0.0))
        now = settle(made.select("window_id", "stream_id", "inst_id", *(F.when(F.get("gone", F.lit(d)), cell(d)).otherwise(F.col(c)).alias(c) for d, c in enumerate(xs)), "gone"))
    return now.drop("gone")
