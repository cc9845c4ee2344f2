"""Masks, and taking out cells, streams and shares of windows by a rule that any SQL engine can repeat.

The hash of a key is the first 32 bits of an MD5, as a share of 1; a cell goes if its share is below the rate.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from streamfill.schema import attributes


#: Beyond so many attributes a step goes through an array: generated code for each would outgrow a method.
WIDE = 24


def share(*parts) -> Column:
    cols = [p if isinstance(p, Column) else F.lit(p) for p in parts]
    return F.conv(F.substring(F.md5(F.concat_ws(":", *(c.cast("string") for c in cols))), 1, 8), 16, 10).cast("long") / float(2**32)


def cell_hash(seed: int, key: Column, dim: int) -> Column:
    return share(seed, key, dim)


def observed(c: str) -> Column:
    return F.col(c).isNotNull().cast("int")


def mask_of(df: DataFrame) -> DataFrame:
    """The keys with m0, m1, ...: 1 where a cell is observed."""
    return df.select("window_id", "inst_id", *(observed(c).alias(f"m{c[1:]}") for c in attributes(df)))


def packed(df: DataFrame) -> Column:
    """Up to 63 attributes' mask as the bits of one number."""
    return reduce(lambda a, b: a.bitwiseOR(b), (F.shiftleft(observed(c).cast("long"), d) for d, c in enumerate(attributes(df))))


def remove_cells(df: DataFrame, rate: float, seed: int = 0) -> tuple[DataFrame, DataFrame]:
    """(df without the removed cells, the removed cells as (window_id, inst_id, dim, truth))."""
    goes = lambda c: F.col(c).isNotNull() & (cell_hash(seed, F.col("inst_id"), int(c[1:])) < rate)
    xs = attributes(df)
    if len(xs) > WIDE:
        below = F.transform(F.array(*xs), lambda v, d: F.when(v.isNotNull(), share(seed, F.col("inst_id"), d) < rate))
        held = df.select("window_id", "stream_id", "inst_id", *xs, below.alias("goes"))
        left = held.select("window_id", "stream_id", "inst_id", *(F.when(~F.get("goes", F.lit(d)), F.col(c)).alias(c) for d, c in enumerate(xs)))
        cut = F.transform(F.array(*xs), lambda v, d: F.when(F.get("goes", d), v))
        return left, held.select("window_id", "inst_id", F.posexplode(cut).alias("dim", "truth")).where("truth is not null")
    left = df.select("window_id", "stream_id", "inst_id", *(F.when(~goes(c), F.col(c)).alias(c) for c in xs))
    cells = F.array(*(F.struct(F.lit(int(c[1:])).alias("dim"), F.when(goes(c), F.col(c)).alias("truth")) for c in xs))
    gone = df.select("window_id", "inst_id", F.explode(cells).alias("c")).select("window_id", "inst_id", "c.dim", "c.truth")
    return left, gone.where("truth is not null")


def keep_streams(df: DataFrame, ratio: float, seed: int = 0) -> DataFrame:
    return df.where(share(seed, F.col("stream_id")) < ratio)


def irregular(df: DataFrame, ratios: tuple[float, ...], seed: int = 0) -> DataFrame:
    """Every window keeps another share of the streams, drawn among `ratios` by the window's hash."""
    turn = F.floor(share(seed, F.col("window_id")) * len(ratios)).cast("int")
    ratio = F.element_at(F.array(*map(F.lit, ratios)), turn + 1)
    return df.where(share(seed + 1, F.col("stream_id"), F.col("window_id")) < ratio)


def cells(df: DataFrame) -> DataFrame:
    """The cell form (window_id, inst_id, dim, val), missing cells included."""
    made = F.array(*(F.struct(F.lit(int(c[1:])).alias("dim"), F.col(c).alias("val")) for c in attributes(df)))
    return df.select("window_id", "inst_id", F.explode(made).alias("c")).select("window_id", "inst_id", "c.dim", "c.val")
