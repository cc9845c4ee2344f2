"""Mean filling and scaling: one aggregation, joined back by window (or by nothing, for the scaler)."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from streamfill.schema import attributes


def means(df: DataFrame, whole: bool = False, empty_dim: str = "zero") -> DataFrame:
    """Observed means of each window, u0, u1, ...; `whole` rounds them down. A dimension that nobody observed has 0, or
    (carry) the mean of the last window before that has one; there is a row for each window, so the window function
    that looks back runs over as many rows."""
    made = lambda c: F.floor(F.avg(c)).cast("double") if whole else F.avg(c)
    us = [f"u{c[1:]}" for c in attributes(df)]
    out = df.groupBy("window_id").agg(*(made(c).alias(u) for c, u in zip(attributes(df), us, strict=True)))
    if empty_dim == "carry":
        back = Window.orderBy("window_id").rowsBetween(Window.unboundedPreceding, 0)
        out = out.withColumns({u: F.last(u, ignorenulls=True).over(back) for u in us})
    elif empty_dim != "zero":
        raise ValueError("empty_dim is zero or carry")
    return out.withColumns({u: F.coalesce(u, F.lit(0.0)) for u in us})


def mean_fill(df: DataFrame, whole: bool = False, empty_dim: str = "zero") -> DataFrame:
    """Missing cells get their window's mean. A missing cell's own row adds nothing to it, so this is the mean of the others."""
    xs = attributes(df)
    return df.join(means(df, whole, empty_dim), "window_id").select("window_id", "stream_id", "inst_id", *(F.coalesce(c, f"u{c[1:]}").alias(c) for c in xs))


@dataclass(frozen=True)
class Scaler:
    """Means and deviations of each attribute; D numbers each, so they go into the plan as constants."""

    mean: tuple[float, ...]
    scale: tuple[float, ...]

    @staticmethod
    def fit(df: DataFrame) -> Scaler:
        """Over observed cells; call it after cells for scoring are removed. A constant attribute has scale 1."""
        xs = attributes(df)
        row = df.agg(*(F.avg(c) for c in xs), *(F.stddev_pop(c) for c in xs)).first()
        return Scaler(tuple(v or 0.0 for v in row[: len(xs)]), tuple(v or 1.0 for v in row[len(xs) :]))

    def transform(self, df: DataFrame) -> DataFrame:
        return df.withColumns({f"x{d}": (F.col(f"x{d}") - m) / s for d, (m, s) in enumerate(zip(self.mean, self.scale, strict=True))})

    def inverse(self, df: DataFrame) -> DataFrame:
        return df.withColumns({f"x{d}": F.col(f"x{d}") * s + m for d, (m, s) in enumerate(zip(self.mean, self.scale, strict=True))})
