"""Which rows of a window are worth carrying: many observed cells, few of them shared with other rows.

A row's importance is the mean over the other rows of (its observed cells less those it shares). With c_d the number
of rows that observe dimension d, that is (n * observed - sum of c_d over its observed d) / (n - 1): one aggregation
in place of the product of the mask with itself.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from streamfill.operators.masks import observed, packed
from streamfill.schema import attributes


def observed_count(df: DataFrame) -> Column:
    xs = attributes(df)
    return sum((observed(c) for c in xs[1:]), observed(xs[0]))


def overlap(df: DataFrame) -> DataFrame:
    """Cells observed in both rows, for every ordered pair of a window (for checks; quadratic in the window)."""
    own = df.select("window_id", "inst_id", packed(df).alias("bits"))
    a, b = own.alias("a"), own.alias("b")
    joined = a.join(b, (F.col("a.window_id") == F.col("b.window_id")) & (F.col("a.inst_id") != F.col("b.inst_id")))
    return joined.select(F.col("a.window_id").alias("window_id"), F.col("a.inst_id").alias("src"), F.col("b.inst_id").alias("dst"), F.bit_count(F.col("a.bits").bitwiseAND(F.col("b.bits"))).alias("shared"), F.bit_count("a.bits").alias("own"))


def pairwise(df: DataFrame) -> DataFrame:
    """Importance by its definition over pairs. Rows with the same mask overlap others alike, so masks are paired, with
    the number of rows of each, and not rows; a row alone in its window is in no pair."""
    own = df.select("window_id", "inst_id", packed(df).alias("bits"))
    masks = own.groupBy("window_id", "bits").agg(F.count("*").alias("n"))
    a, b = masks.alias("a"), masks.alias("b")
    # a row's pair with itself adds nothing: it shares all its cells
    unshared = F.bit_count("a.bits") - F.bit_count(F.col("a.bits").bitwiseAND(F.col("b.bits")))
    phi = a.join(b, F.col("a.window_id") == F.col("b.window_id")).groupBy("a.window_id", "a.bits").agg(F.sum(F.col("b.n") * unshared).alias("total"), (F.sum("b.n") - 1).alias("others"))
    phi = phi.where("others > 0").select("window_id", "bits", (F.col("total") / F.col("others")).alias("phi"))
    return own.join(phi, ["window_id", "bits"]).select("window_id", "inst_id", "phi")


def scores(df: DataFrame, normalise: bool = True) -> DataFrame:
    """df with phi. Rows that observe nothing have 0; a row alone in its window has its observed cells, at most D - 1.
    Normalised, it is divided by D - 1 (one attribute: by 1)."""
    xs = attributes(df)
    seen = df.groupBy("window_id").agg(F.count("*").alias("n"), *(F.count(c).alias(f"c{c[1:]}") for c in xs))
    out = df.join(seen, "window_id")
    shared = sum((F.when(F.col(c).isNotNull(), F.col(f"c{c[1:]}")).otherwise(0) for c in xs), F.lit(0))
    own = observed_count(df)
    phi = F.when(F.col("n") == 1, F.least(own, F.lit(max(1, len(xs) - 1))).cast("double")).otherwise((F.col("n") * own - shared) / (F.col("n") - 1))
    return out.withColumn("phi", phi / max(1, len(xs) - 1) if normalise else phi).drop("n", *(f"c{c[1:]}" for c in xs))


def bounded(df: DataFrame, eta: float, max_cache: int) -> DataFrame:
    """Rows that reach eta, at most so many a window: the most important and then the latest first."""
    kept = select(df, eta)
    order = Window.partitionBy("window_id").orderBy(F.desc("phi"), F.desc("inst_id"))
    return kept.withColumn("place", F.row_number().over(order)).where(F.col("place") <= max_cache).drop("place")


def select(df: DataFrame, eta: float = 0.6, mode: str = "absolute", strict: bool = False) -> DataFrame:
    """Rows whose normalised importance reaches eta; in mode quantile, the top 1 - eta of each window."""
    scored = scores(df)
    if mode == "quantile":
        cut = scored.groupBy("window_id").agg(F.percentile_approx("phi", eta).alias("cut"))
        scored = scored.join(cut, "window_id")
        return scored.where(F.col("phi") >= F.col("cut")).drop("cut")
    return scored.where(F.col("phi") > eta if strict else F.col("phi") >= eta)
