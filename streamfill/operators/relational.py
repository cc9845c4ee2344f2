"""Joins and rankings that the methods and their tests lean on."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from streamfill.schema import attributes, seconds


def join(left: DataFrame, right: DataFrame, on, how: str = "inner", strategy: str | None = None) -> DataFrame:
    """An equi-join; strategy broadcast, merge, shuffle_hash or none, which leaves it to the planner."""
    return left.join(right.hint(strategy) if strategy else right, on, how)


def interval_join(left: DataFrame, right: DataFrame, delta: int, *, by: str | None = None) -> DataFrame:
    """Rows of right within delta (in units of column t, whole numbers) of a row of left, on another stream.

    Time is cut into steps of delta; a right row stands in its step and both beside it, so this is an equi-join."""
    width = max(1, delta)
    lt, rt = left.withColumn("step", F.floor(F.col("t") / width)), right.withColumn("step", F.floor(F.col("t") / width))
    rt = rt.select(*(F.col(c).alias(f"r_{c}") for c in right.columns), F.explode(F.array(*(F.col("step") + k for k in (-1, 0, 1)))).alias("step"))
    out = lt.join(rt, "step").where(F.abs(F.col("t") - F.col("r_t")) <= delta).drop("step")
    return out.where(F.col(by) != F.col(f"r_{by}")) if by else out


def asof(left: DataFrame, right: DataFrame, by: str, value: str) -> DataFrame:
    """left with the last value of right at or before its time t, per `by`: one sort of both sides together."""
    both = left.select(by, "t", F.lit(1).alias("side"), F.lit(None).cast(right.schema[value].dataType).alias(value), F.struct(*left.columns).alias("row")).unionByName(
        right.select(by, "t", F.lit(0).alias("side"), value), allowMissingColumns=True
    )
    w = Window.partitionBy(by).orderBy("t", "side").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(value, F.last(value, ignorenulls=True).over(w)).where("side = 1").select("row.*", value)


def gaps(df: DataFrame, by: str, time_col: str, *ties: str) -> DataFrame:
    """Seconds since the stream's last row."""
    w = Window.partitionBy(by).orderBy("t", *ties)
    return df.withColumn("t", seconds(F.col(time_col))).withColumn("gap", F.col("t") - F.lag("t").over(w))


def rolling(df: DataFrame, by: list[str], order: list, value: str, rows: int) -> DataFrame:
    w = Window.partitionBy(*by).orderBy(*order).rowsBetween(-(rows - 1), 0)
    return df.withColumns({"r_sum": F.sum(value).over(w), "r_n": F.count(value).over(w), "r_min": F.min(value).over(w), "r_max": F.max(value).over(w)})


def topk(df: DataFrame, by: list[str], order: list[Column], k: int) -> DataFrame:
    """The first k rows of each group; ranks are cut before the shuffle."""
    w = Window.partitionBy(*by).orderBy(*order)
    return df.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def ranks(df: DataFrame, by: list[str], order: list[Column]) -> DataFrame:
    w = Window.partitionBy(*by).orderBy(*order)
    return df.withColumns({"row_number": F.row_number().over(w), "rank": F.rank().over(w), "dense_rank": F.dense_rank().over(w), "ntile": F.ntile(4).over(w)})


def locf(df: DataFrame, xs: list[str]) -> DataFrame:
    """Missing cells get the stream's last observed value, of any earlier window."""
    w = Window.partitionBy("stream_id").orderBy("inst_id").rowsBetween(Window.unboundedPreceding, 0)
    return df.withColumns({c: F.last(c, ignorenulls=True).over(w) for c in xs})


def linear(df: DataFrame, xs: list[str], position: str = "inst_id") -> DataFrame:
    """Missing cells get the point of the line between the observed values before and after; at the ends, the nearest."""
    before = Window.partitionBy("stream_id").orderBy(position).rowsBetween(Window.unboundedPreceding, 0)
    after = Window.partitionBy("stream_id").orderBy(position).rowsBetween(0, Window.unboundedFollowing)
    out = {}
    for c in xs:
        at = F.when(F.col(c).isNotNull(), F.struct(F.col(position).alias("t"), F.col(c).alias("v")))
        p, n = F.last(at, ignorenulls=True).over(before), F.first(at, ignorenulls=True).over(after)
        line = p["v"] + (n["v"] - p["v"]) * (F.col(position) - p["t"]) / (n["t"] - p["t"])
        out[c] = F.coalesce(F.col(c), line, p["v"], n["v"])
    return df.withColumns(out)


def collect_chunk(df: DataFrame) -> DataFrame:
    """(window_id, rows): a window's rows as one array of structs (inst_id, stream_id, x), in order of their ids. For
    windows that fit in a task; larger ones are split first."""
    row = F.struct("inst_id", "stream_id", F.array(*attributes(df)).alias("x"))
    return df.groupBy("window_id").agg(F.sort_array(F.collect_list(row)).alias("rows"))
