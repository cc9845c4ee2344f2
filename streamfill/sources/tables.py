"""Scans of the given tables, other formats, streams of files, and the fixtures cut from the tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from streamfill.schema import InstanceSchema, TimeAxis, attributes, seconds

#: Fixed: the attributes of the event fixtures, in order.
EVENT_TYPES = ("click", "error", "purchase", "signup", "view")
ROLES = ("assistant", "system", "user")
HOUR, DAY = 3600, 86400
#: Bits of an instance id for its stream, and for a turn of a conversation or a line of an order.
STREAM_BITS, TURN_BITS = 43, 20


def joined_id(high: Column, low: Column, bits: int) -> Column:
    """One number of two, different for different pairs: the lower takes so many bits, and what has no room raises."""
    fits = low.between(0, (1 << bits) - 1) & high.between(-(1 << 63 - bits), (1 << 63 - bits) - 1)
    made = F.shiftleft(high.cast("long"), bits).bitwiseOR(low.cast("long"))
    return F.when(high.isNull() | low.isNull(), F.lit(None).cast("long")).when(fits, made).otherwise(F.raise_error(F.lit("an id has no room in the bits kept for it")).cast("long"))


def bucket_of(inst_id: Column) -> Column:
    """The time bucket of an instance id."""
    return F.shiftright(inst_id, STREAM_BITS)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read(spark: SparkSession, fmt: str, path: str, schema: StructType | str) -> DataFrame:
    """Any format of Spark's readers, the schema given so that nothing is inferred."""
    return spark.read.format(fmt).schema(schema).load(path)


def stream_files(spark: SparkSession, path: str, schema: StructType, max_files: int = 1, time_col: str = "ts") -> DataFrame:
    """Parquet files as a stream. Timestamps without zone become instants (in UTC sessions the same), as watermarks need them."""
    df = spark.readStream.schema(schema).option("maxFilesPerTrigger", max_files).parquet(path)
    return df.withColumn(time_col, F.col(time_col).cast("timestamp"))


def rate(spark: SparkSession, rows_per_second: int = 10) -> DataFrame:
    return spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()


def from_messages(messages: DataFrame, schema: StructType | str) -> DataFrame:
    """Readings out of rows shaped like a message queue's (key, value, timestamp), value holding JSON."""
    return messages.select(F.from_json(F.col("value").cast("string"), schema).alias("v"), "timestamp").select("v.*", "timestamp")


def assemble(readings: DataFrame, keys: list[str], attribute: str, value: str, names: tuple, how: str = "avg") -> DataFrame:
    """Rows of one reading each to instances: one column x<d> for each name, by conditional aggregation, which a stream allows too."""
    agg = {"avg": F.avg, "sum": F.sum, "max": F.max, "min": F.min, "last": F.last}[how]
    return readings.groupBy(*keys).agg(*(agg(F.when(F.col(attribute) == n, F.col(value))).alias(f"x{d}") for d, n in enumerate(names)))


def ev(spark: SparkSession, sf_dir: str, bucket: int = HOUR, window: int = DAY) -> DataFrame:
    """Sparse concurrent streams: a user's mean value by type of event in a bucket of time, in whole ten-thousandths."""
    e = table(spark, sf_dir, "events")
    cents = F.round(F.col("value") * 100).cast("long")
    e = e.select("user_id", F.floor(seconds(F.col("ts")) / bucket).cast("long").alias("b"), "event_type", cents.alias("c"))
    mean = lambda t: F.floor(F.try_divide(F.sum(F.when(F.col("event_type") == t, F.col("c"))) * 100, F.count_if(F.col("event_type") == t)))
    return e.groupBy("user_id", "b").agg(*(mean(t).cast("double").alias(f"x{d}") for d, t in enumerate(EVENT_TYPES))).select(
        F.floor(F.col("b") * bucket / window).cast("long").alias("window_id"), F.col("user_id").alias("stream_id"),
        joined_id(F.col("b"), F.col("user_id"), STREAM_BITS).alias("inst_id"), *(f"x{d}" for d in range(len(EVENT_TYPES))),
    )


def evj(spark: SparkSession, sf_dir: str, window: int = DAY) -> DataFrame:
    """ev with a sixth attribute out of the events' JSON."""
    e = table(spark, sf_dir, "events").select("user_id", F.floor(seconds(F.col("ts")) / HOUR).cast("long").alias("b"), F.get_json_object("props", "$.k").cast("double").alias("k"))
    k = e.groupBy(joined_id(F.col("b"), F.col("user_id"), STREAM_BITS).alias("inst_id")).agg(F.floor(F.avg("k") * 10000).alias("x5"))
    return ev(spark, sf_dir, HOUR, window).join(k, "inst_id").select("window_id", "stream_id", "inst_id", "x0", "x1", "x2", "x3", "x4", F.col("x5").cast("double").alias("x5"))


LI_ATTRIBUTES = ("l_quantity", "l_extendedprice", "l_discount", "l_tax", "net", "charge", "rebate", "unit", "p_retailprice", "p_size", "o_totalprice")


def li_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Line items with what follows from them; part is small beside them, and a broadcast is left to the size statistics."""
    li = table(spark, sf_dir, "lineitem")
    price, kept = F.col("l_extendedprice"), 1 - F.col("l_discount")
    li = li.withColumns({"net": price * kept, "charge": price * kept * (1 + F.col("l_tax")), "rebate": price * F.col("l_discount"), "unit": price / F.col("l_quantity")})
    part = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("l_partkey"), "p_retailprice", "p_size")
    orders = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_totalprice")
    return li.join(part, "l_partkey").join(orders, "l_orderkey")


def li(spark: SparkSession, sf_dir: str, window: int = 30 * DAY) -> DataFrame:
    """Dense heterogeneous streams of suppliers; derived attributes go with one another."""
    rows = li_rows(spark, sf_dir)
    # an order has the same line number several times here: repeats are numbered by what they hold
    again = F.row_number().over(Window.partitionBy("l_orderkey", "l_linenumber").orderBy("l_shipdate", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax"))
    ident = joined_id(F.col("l_orderkey"), F.col("l_linenumber") * (1 << TURN_BITS // 2) + again, TURN_BITS)
    return InstanceSchema("l_suppkey", TimeAxis("l_shipdate", window), LI_ATTRIBUTES).chunks(rows.withColumn("inst_id", ident), F.col("inst_id"))


def emb(spark: SparkSession, sf_dir: str, window: int = 150, dims: int = 64, sparsity: float = 0.856) -> DataFrame:
    """One wide homogeneous stream by index; a share of the cells is taken out beforehand."""
    from streamfill.operators.masks import share

    e = table(spark, sf_dir, "embeddings").select("vec_id", F.transform("embedding", lambda v, d: F.when(share(7, F.col("vec_id"), d) >= sparsity, v.cast("double"))).alias("kept"))
    return e.select(F.floor(F.col("vec_id") / window).cast("long").alias("window_id"), F.lit(0).cast("long").alias("stream_id"), F.col("vec_id").alias("inst_id"), *(F.get("kept", F.lit(d)).alias(f"x{d}") for d in range(dims)))


def lowrank(spark: SparkSession, sf_dir: str, window: int = 150, dims: int = 16, rank: int = 3) -> DataFrame:
    """One homogeneous stream whose attributes are mixtures of three hidden ones."""
    import hashlib

    mix = [[int(hashlib.md5(f"{d}:{r}".encode()).hexdigest()[:8], 16) / 2**31 - 1 for r in range(rank)] for d in range(dims)]
    e = table(spark, sf_dir, "embeddings")
    x = lambda d: sum((F.get("embedding", F.lit(r)).cast("double") * b for r, b in enumerate(mix[d])), F.lit(0.0))
    return e.select(F.floor(F.col("vec_id") / window).cast("long").alias("window_id"), F.lit(0).cast("long").alias("stream_id"), F.col("vec_id").alias("inst_id"), *(x(d).alias(f"x{d}") for d in range(dims)))


def doc(spark: SparkSession, sf_dir: str, window: int = 250) -> DataFrame:
    """Text measures with natural gaps: what the labels rate is known for some documents only."""
    d = table(spark, sf_dir, "documents").join(table(spark, sf_dir, "labels"), "doc_id", "left")
    count = lambda p: F.log1p(F.regexp_count("text", F.lit(p)).cast("double"))
    xs = [F.log1p(F.col("n_chars").cast("double")), count(r"\S+"), count("\n"), count("[0-9]"), count("[A-Z]"), count("[.,;:!?]"), F.col("quality").cast("double"), F.col("toxic").cast("double")]
    return d.select(F.floor(F.col("doc_id") / window).cast("long").alias("window_id"), F.col("source").alias("stream_id"), F.col("doc_id").alias("inst_id"), *(x.alias(f"x{k}") for k, x in enumerate(xs)))


def conv(spark: SparkSession, sf_dir: str, window: int = 2) -> DataFrame:
    """Short streams by index; windows are smaller than most graphs' K."""
    c = table(spark, sf_dir, "conversations")
    return c.select(F.floor(F.col("turn") / window).cast("long").alias("window_id"), F.col("conv_id").alias("stream_id"), joined_id(F.col("conv_id"), F.col("turn"), TURN_BITS).alias("inst_id"), *(F.when(F.col("role") == r, F.length("text").cast("double")).alias(f"x{k}") for k, r in enumerate(ROLES)))


def roll(spark: SparkSession, sf_dir: str, window: int = DAY) -> DataFrame:
    """Smooth in time: rolling means of a user's last ten values of each type."""
    e = table(spark, sf_dir, "events")
    w = Window.partitionBy("user_id", "event_type").orderBy("ts", "event_id").rowsBetween(-9, 0)
    e = e.withColumn("m", F.avg("value").over(w)).withColumn("b", F.floor(seconds(F.col("ts")) / HOUR).cast("long"))
    rows = assemble(e, ["user_id", "b"], "event_type", "m", EVENT_TYPES)
    return rows.select(F.floor(F.col("b") * HOUR / window).cast("long").alias("window_id"), F.col("user_id").alias("stream_id"), joined_id(F.col("b"), F.col("user_id"), STREAM_BITS).alias("inst_id"), *(f"x{d}" for d in range(len(EVENT_TYPES))))


FIXTURES = {"ev": ev, "evj": evj, "li": li, "emb": emb, "lowrank": lowrank, "doc": doc, "conv": conv, "roll": roll}


def fixture(spark: SparkSession, sf_dir: str, name: str, **options) -> DataFrame:
    df = FIXTURES[name](spark, sf_dir, **options)
    return df.select(F.col("window_id"), F.col("stream_id").cast("string").alias("stream_id"), "inst_id", *attributes(df))
