"""SQL functions, the replayed stream, readers."""

import pytest

from streamfill.functions.sqlfuncs import register
from streamfill.sources import tables
from streamfill.sources.replay import replay
from streamfill.sources.sinks import to_memory


def test_sql_functions(spark):
    register(spark)
    r = spark.sql("SELECT or_count(array(1D, NULL, 2D)) AS a, oor(array(1D, NULL, 2D), array(NULL, 1D, 3D)) AS b, euclid(array(0D, 3D), array(4D, 0D)) AS c").first()
    assert (r.a, r.b, r.c) == (2, 1, 5.0)
    r = spark.sql("SELECT mae(t, v) AS a, mre(t, v) AS b FROM VALUES (1D, 2D), (3D, 1D) AS d(t, v)").first()
    assert (r.a, r.b) == (1.5, 0.75)
    assert spark.sql("SELECT dim, val FROM explode_cells(array(5D, NULL))").collect() == [(0, 5.0), (1, None)]
    spark.createDataFrame([(0, i, [float(i), None if i == 2 else 1.0], 1) for i in range(4)], "window_id int, inst_id long, x array<double>, k int").createOrReplaceTempView("chunk")
    got = spark.sql("SELECT src, dst FROM knn_block(TABLE(SELECT window_id, inst_id, x, k FROM chunk) PARTITION BY window_id)").collect()
    assert {(r.src, r.dst) for r in got} == {(0, 1), (1, 0), (2, 1), (3, 2)}


def test_replay_keeps_order_and_rows(spark, sf_dir):
    q = to_memory(replay(spark, f"{sf_dir}/events.parquet", rows=300).select("event_id"), "replayed")
    q.awaitTermination(60)
    got = [r.event_id for r in spark.table("replayed").collect()]
    q.stop()
    assert got and got == sorted(got) and len(set(got)) == len(got)


def test_replay_is_read_by_spark_in_whole_batches(spark, sf_dir, tmp_path, monkeypatch):
    import pyarrow.dataset

    monkeypatch.setattr(pyarrow.dataset, "dataset", lambda *a, **b: pytest.fail("the table was read by the driver"))
    met = []
    for rows, file_rows in ((300, 1000), (300, 70)):
        stream, sizes = replay(spark, f"{sf_dir}/events.parquet", rows=rows, file_rows=file_rows), {}
        q = stream.writeStream.foreachBatch(lambda df, k, to=sizes: to.update({k: [r.event_id for r in df.select("event_id").collect()]})).option("checkpointLocation", f"{tmp_path}/{file_rows}").trigger(availableNow=True).start()
        q.awaitTermination(120)
        met.append([sorted(sizes[k]) for k in sorted(sizes)])
    want = [r.event_id for r in tables.table(spark, sf_dir, "events").orderBy("ts", "event_id").collect()]
    assert met[0] == met[1] and sorted(sum(met[0], [])) == sorted(want)
    assert [len(b) for b in met[0]] == [300] * (len(want) // 300) + [len(want) % 300] * bool(len(want) % 300)
    assert sum(met[0], []) == sum((sorted(want[at : at + 300]) for at in range(0, len(want), 300)), [])


def test_formats_and_streams(spark, sf_dir, tmp_path):
    e = tables.table(spark, sf_dir, "events").limit(20).select("event_id", "value")
    for fmt in ("json", "orc", "csv"):
        e.write.format(fmt).save(f"{tmp_path}/{fmt}")
        assert tables.read(spark, fmt, f"{tmp_path}/{fmt}", "event_id long, value double").count() == 20
    raw = tables.table(spark, sf_dir, "events")
    raw.coalesce(1).write.parquet(f"{tmp_path}/stream")
    q = to_memory(tables.stream_files(spark, f"{tmp_path}/stream", raw.schema), "files")
    q.awaitTermination(120)
    assert spark.table("files").count() == raw.count() and dict(spark.table("files").dtypes)["ts"] == "timestamp"
    m = spark.createDataFrame([('{"a": 1}',)], "value string").selectExpr("cast(value as binary) value", "current_timestamp() timestamp")
    assert tables.from_messages(m, "a int").first().a == 1
    assert tables.rate(spark).isStreaming


@pytest.mark.parametrize("name", sorted(tables.FIXTURES))
def test_fixtures(spark, sf_dir, name):
    df = tables.fixture(spark, sf_dir, name)
    assert df.count() > 0 and df.select("inst_id").distinct().count() == df.count()
