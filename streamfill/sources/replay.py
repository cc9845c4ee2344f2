"""A table replayed as a stream in the order of its event time, a fixed number of rows a batch.

Spark sorts the table once into files in the shared folder, a file for each batch or, where a batch is larger than
FILE_ROWS, several; the stream is Spark's own over these files. The driver holds names of files only, executors read the
rows, and a restart from a checkpoint over the same folder goes on where the last commit was.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from streamfill.sources.durable import settle, shared_folder

#: Rows a file holds at most.
FILE_ROWS = 500_000
#: Bits of Spark's increasing ids for a row's place in its partition.
PLACE_BITS = 33


def numbered(df: DataFrame, order: str) -> DataFrame:
    """df with a column `replay_row`, from 0 in the order given. Rows are sorted by ranges, and the rows of the ranges before
    are added up; a range has one row in that sum. Settled before, so that numbers stay as they were drawn."""
    rows = settle(df.orderBy(order).withColumn("replay_row", F.monotonically_increasing_id()))
    part = F.shiftright("replay_row", PLACE_BITS)
    earlier = Window.orderBy("replay_part").rowsBetween(Window.unboundedPreceding, -1)
    before = rows.groupBy(part.alias("replay_part")).agg(F.count("*").alias("n")).select("replay_part", F.coalesce(F.sum("n").over(earlier), F.lit(0)).alias("before"))
    placed = rows.withColumn("replay_part", part).join(F.broadcast(before), "replay_part")
    return placed.select(*df.columns, (F.col("before") + F.col("replay_row").bitwiseAND(F.lit((1 << PLACE_BITS) - 1))).alias("replay_row"))


def replay(spark: SparkSession, path: str, order: str = "ts", rows: int = 1000, file_rows: int = FILE_ROWS) -> DataFrame:
    """A stream of the Parquet table at path. A batch has `rows` rows, the last what is left; within a batch of one file
    they come in order."""
    files = -(-rows // file_rows)
    each = -(-rows // files)
    df = spark.read.parquet(path)
    # a batch takes a fixed number of files, so all but the last have just as many
    file = F.expr(f"replay_row div {rows} * {files} + replay_row % {rows} div {each}")
    dealt = numbered(df, order).withColumn("replay_file", file)
    folder = f"{shared_folder(spark)}/replay-{uuid.uuid4().hex}"
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    dealt.repartition(n, "replay_file").sortWithinPartitions("replay_file", "replay_row").drop("replay_row").write.partitionBy("replay_file").parquet(folder)
    _dated(spark, folder)
    return spark.readStream.schema(df.schema).option("maxFilesPerTrigger", min(files, (1 << 31) - 1)).parquet(folder).select(*df.columns)


def _dated(spark: SparkSession, folder: str) -> None:
    """Files by their number a second apart, as a stream takes the oldest first."""
    root = spark._jvm.org.apache.hadoop.fs.Path(folder)
    store = root.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf())
    found = []
    for part in store.listStatus(root):
        if "=" in (name := part.getPath().getName()):
            found += [(int(name.split("=")[1]), s.getPath()) for s in store.listStatus(part.getPath()) if s.getPath().getName().endswith(".parquet")]
    for number, file in found:
        store.setTimes(file, 1_000_000_000_000 + number * 1000, -1)
