"""Propagation over edge tables: one join and one aggregation a step.

Nodes are chunks; weighted edges come from graph.normalise. A null in the original chunk marks a missing cell, so
the bound condition is a coalesce.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from streamfill.schema import attributes
from streamfill.sources.durable import settle


def feature_step(nodes: DataFrame, weighted: DataFrame) -> DataFrame:
    """Every row becomes the weighted sum of its neighbours; rows without any keep what they are."""
    xs = attributes(nodes)
    far = nodes.select("window_id", F.col("inst_id").alias("dst"), *xs)
    sums = weighted.join(far, ["window_id", "dst"]).groupBy("window_id", F.col("src").alias("inst_id")).agg(*(F.sum(F.col("w") * F.col(c)).alias(f"s{c[1:]}") for c in xs))
    return nodes.join(sums, ["window_id", "inst_id"], "left").select("window_id", "stream_id", "inst_id", *(F.coalesce(f"s{c[1:]}", c).alias(c) for c in xs))


def bound(original: DataFrame, now: DataFrame) -> DataFrame:
    """Observed cells go back to their values."""
    xs = attributes(original)
    old = original.select("window_id", "inst_id", *(F.col(c).alias(f"o{c[1:]}") for c in xs))
    return now.join(old, ["window_id", "inst_id"]).select("window_id", "stream_id", "inst_id", *(F.coalesce(f"o{c[1:]}", c).alias(c) for c in xs))


def feature_propagate(original: DataFrame, filled: DataFrame, weighted: DataFrame, iters: int = 40, tol: float | None = None, every: int = 5, bounded: bool = True) -> DataFrame:
    """Steps until `iters`, or until no cell moves by tol between two cuts. Every few steps the rows are written to the
    shared folder, which keeps the plan short and a lost executor cheap."""
    xs = attributes(original)
    nodes, last = filled, None
    weighted = settle(weighted) if iters > 1 else weighted
    for step in range(1, iters + 1):
        nodes = feature_step(nodes, weighted)
        nodes = bound(original, nodes) if bounded else nodes
        if step % every == 0 and step < iters:
            nodes = settle(nodes)
            if tol is not None and last is not None:
                gap = nodes.alias("a").join(last.alias("b"), ["window_id", "inst_id"]).agg(F.max(F.greatest(*(F.abs(F.col(f"a.{c}") - F.col(f"b.{c}")) for c in xs), F.lit(0.0)))).first()[0]
                if (gap or 0.0) < tol:
                    break
            last = nodes
    return nodes


def message_step(nodes: DataFrame, correlated: DataFrame, matrix: Sequence[Sequence[float]] | None = None) -> DataFrame:
    """Every row becomes the sum of c * x over its neighbours, times a matrix (identity if none); c is the edges' column w."""
    xs = attributes(nodes)
    out = feature_step(nodes, correlated)
    if matrix is None:
        return out
    mixed = [sum((F.col(c) * float(matrix[i][j]) for i, c in enumerate(xs)), F.lit(0.0)) for j in range(len(xs))]
    return out.select("window_id", "stream_id", "inst_id", *(m.alias(c) for m, c in zip(mixed, xs, strict=True)))
