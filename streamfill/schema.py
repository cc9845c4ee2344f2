"""The shape of a chunk: window_id, stream_id, inst_id and one double column for each attribute, null where missing.

Scalar columns keep every relational step inside generated code; kernels get the same rows as Arrow batches. A NaN is
made null when read, so null is the only mark of a missing cell.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

KEYS = ("window_id", "stream_id", "inst_id")


def attributes(df: DataFrame) -> list[str]:
    """The attribute columns x0, x1, ... in order."""
    return sorted((c for c in df.columns if c[:1] == "x" and c[1:].isdigit()), key=lambda c: int(c[1:]))


def seconds(ts: Column) -> Column:
    """Whole seconds since 1970 of a timestamp without zone, whatever the session's zone."""
    return F.timestamp_diff("SECOND", F.lit("1970-01-01 00:00:00").cast("timestamp_ntz"), ts.cast("timestamp_ntz"))


@dataclass(frozen=True)
class TimeAxis:
    """Where a row stands: in event time (a timestamp column, length in seconds) or by index (a whole number)."""

    column: str
    length: int
    kind: str = "event"

    def position(self) -> Column:
        return seconds(F.col(self.column)) if self.kind == "event" else F.col(self.column).cast("long")

    def window(self) -> Column:
        """Half-open tumbling windows [a * length, (a + 1) * length)."""
        return F.floor(self.position() / self.length).cast("long")


@dataclass(frozen=True)
class InstanceSchema:
    """What of a source is the stream, the time, and the attributes, in their order."""

    stream: str
    axis: TimeAxis
    attributes: tuple[str, ...]

    def chunks(self, df: DataFrame, inst_id: Column | None = None) -> DataFrame:
        """One instance a row, with its window; stream and time are merged into the rows. Attributes of any numeric or boolean type."""
        number = lambda c: F.when(~F.isnan(v := F.col(c).cast("double")) & (F.abs(v) != float("inf")), v)
        ident = F.xxhash64(self.stream, self.axis.column) if inst_id is None else inst_id
        return df.select(
            self.axis.window().alias("window_id"), F.col(self.stream).alias("stream_id"), ident.alias("inst_id"),
            *(number(c).alias(f"x{d}") for d, c in enumerate(self.attributes)),
        )
