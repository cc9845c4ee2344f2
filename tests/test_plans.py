"""Plans against each other and against the SQL beside them."""

import glob
import os

import numpy as np
import pytest
from pyspark.sql import functions as F

from streamfill.operators import fill, graph, masks, propagate, relational, windows
from streamfill.plans import catalog, continuous, surface, workloads  # noqa: F401
from streamfill.plans.impute import Options, run_windows, snapshot
from streamfill.schema import InstanceSchema, TimeAxis, attributes
from streamfill.sources.tables import fixture


def rows(df):
    names = sorted(df.columns)
    cell = lambda v: None if v is None or v != v else (round(float(v), 6) + 0.0 if isinstance(v, (float, int)) and not isinstance(v, bool) else v)
    return sorted((tuple(cell(r[c]) for c in names) for r in df.to_dict("records")), key=str)


@pytest.fixture(scope="module")
def duck(sf_dir):
    import duckdb

    con = duckdb.connect()
    for p in glob.glob(f"{sf_dir}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(p)[:-8]} AS SELECT * FROM '{p}'")
    return con


@pytest.mark.parametrize("name", sorted(catalog.ORACLES))
def test_query_matches_sql(spark, sf_dir, duck, name):
    import pandas as pd

    got, want = (catalog.QUERIES | workloads.QUERIES)[name](spark, sf_dir).toPandas(), duck.sql(catalog.ORACLES[name]).df()
    want = want.astype(object).where(pd.notna(want), None)
    got = got.astype(object).where(pd.notna(got), None)
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got) == rows(want)


def test_window_kernel_equals_relational_plan(spark, sf_dir):
    df = fixture(spark, sf_dir, "lowrank")
    left, _ = masks.remove_cells(df, 0.3, 3)
    filled = fill.mean_fill(left)
    weighted = graph.normalise(graph.knn(filled, 10))
    a = propagate.feature_propagate(left, filled, weighted, 7).orderBy("inst_id").toPandas()
    b = run_windows(left, {0: Options(method="fp", iters=7)}).orderBy("inst_id").toPandas()
    assert np.abs(a[attributes(df)].to_numpy() - b[attributes(df)].to_numpy()).max() < 1e-8


def test_snapshot_keeps_observed_cells(spark, sf_dir):
    df = fixture(spark, sf_dir, "doc")
    out = snapshot(df, "propnet", epochs=5, max_rows=100).orderBy("inst_id").toPandas()
    old = df.orderBy("inst_id").toPandas()
    xs = attributes(df)
    assert len(out) == len(old) and not out[xs].isna().any().any()
    seen = ~old[xs].isna().to_numpy()
    assert np.array_equal(out[xs].to_numpy()[seen], old[xs].to_numpy()[seen])
    assert np.array_equal(np.stack(out.is_imputed), ~seen)


def test_snapshot_keeps_every_row(spark):
    rows = [(1, "a", 5, 1.0, None), (1, "a", 5, None, 4.0), (1, "a", 5, 3.0, 2.0), (None, "b", 6, None, 1.0), (None, "b", 7, 2.0, None), (2, None, None, 1.0, None)]
    df = spark.createDataFrame(rows, "window_id long, stream_id string, inst_id long, x0 double, x1 double")
    for method in ("mean", "propnet", "fp", "knn"):
        out = snapshot(df, method, epochs=3).collect()
        assert len(out) == len(rows), method
        assert sorted(str((r.window_id, r.inst_id, *r.is_imputed)) for r in out) == sorted(str((w, i, a is None, b is None)) for w, _, i, a, b in rows)
        assert {(r.x0, r.x1) for r in out if r.window_id == 1} >= {(3.0, 2.0)}
    assert {r.x0 for r in snapshot(df, "mean").where("window_id is null").collect()} == {2.0}


def test_blocks_find_the_same_neighbours(spark, sf_dir):
    df = fixture(spark, sf_dir, "lowrank")
    plain = lambda d: sorted((r.window_id, r.src, r.dst, r["rank"]) for r in d.collect())
    for metric in ("euclidean", "cosine"):
        whole = plain(graph.nearest(df, 7, metric))
        assert whole == plain(graph.nearest(df, 7, metric, block_rows=40))
        near = graph.pairs(df, metric).toPandas().sort_values(["window_id", "src", "dist", "dst"]).groupby(["window_id", "src"]).head(7)
        assert {x[:3] for x in whole} == set(near[["window_id", "src", "dst"]].itertuples(index=False, name=None))


def test_gramian_imputers_equal_the_kernels(spark, sf_dir):
    from streamfill.operators import regress

    left, _ = masks.remove_cells(fixture(spark, sf_dir, "doc"), 0.3, 3)
    xs = attributes(left)
    for made, method, more in ((regress.mice(left, 2), "mice", {"rounds": 2}), (regress.mf(left, 3, 4), "mf", {"rank": 3})):
        a = made.orderBy("inst_id").toPandas()[xs].to_numpy()
        if method == "mf":
            from streamfill.functions import kernels

            whole = left.orderBy("window_id", "inst_id").toPandas()
            b = np.concatenate([kernels.mf(g[xs].to_numpy(float), 3, iters=4) for _, g in whole.groupby("window_id")])
            a = made.orderBy("window_id", "inst_id").toPandas()[xs].to_numpy()
        else:
            b = run_windows(left, {0: Options(method=method, **more)}).orderBy("inst_id").toPandas()[xs].to_numpy()
        assert np.allclose(a, b, rtol=1e-6, atol=1e-6), method


def test_ids_do_not_meet(spark):
    from streamfill.sources.tables import STREAM_BITS, bucket_of, joined_id

    rows = [(480_000, 10_000_000), (480_001, 0), (480_000, 20_000_000), (480_002, 0), (-3, 5), (480_000, (1 << STREAM_BITS) - 1)]
    df = spark.createDataFrame(rows, "b long, u long").withColumn("id", joined_id(F.col("b"), F.col("u"), STREAM_BITS)).withColumn("back", bucket_of(F.col("id")))
    got = df.collect()
    assert len({r.id for r in got}) == len(rows) and all(r.back == r.b for r in got)
    with pytest.raises(Exception, match="no room"):
        spark.createDataFrame([(1, 1 << STREAM_BITS)], "b long, u long").select(joined_id(F.col("b"), F.col("u"), STREAM_BITS)).collect()


def test_shards_are_independent_chains(spark, sf_dir):
    df = fixture(spark, sf_dir, "ev")
    out = continuous.run(df, {0: Options(mode="dual_carry", epochs=3, eta=0.2)}, shards=4).toPandas()
    assert len(out) == df.count() and out.cached.max() > 0


def test_windows_side_by_side_equal_the_chain(spark, sf_dir):
    df = fixture(spark, sf_dir, "ev").where("window_id < 19742")
    options = {0: Options(mode="data_carry", epochs=3, eta=0.25), 1: Options(mode="all", method="mf"), 2: Options(mode="dual_carry", epochs=3, eta=0.25), 3: Options(mode="periodic", method="fp")}
    order = lambda d: d.orderBy("cfg", "inst_id").toPandas()
    a, b = order(continuous.run(df, options)), order(continuous.run(df, options, side_by_side=False))
    xs = attributes(df)
    assert len(a) == len(b) == 4 * df.count() and a.cached.max() > 0
    assert np.array_equal(a[["cfg", "window_id", "inst_id", "cached", "best_epoch"]], b[["cfg", "window_id", "inst_id", "cached", "best_epoch"]])
    assert np.allclose(a[xs], b[xs], rtol=1e-9)


def test_stream_equals_replay(spark, sf_dir):
    live = workloads.stream_dual_carry(spark, sf_dir).where("stream_id <> 'end'").orderBy("inst_id").toPandas()
    df = fixture(spark, sf_dir, "ev")
    scaler = fill.Scaler.fit(df)
    batch = continuous.run(scaler.transform(df), {0: Options(mode="dual_carry", epochs=25, eta=0.25)})
    batch = scaler.inverse(batch).orderBy("inst_id").toPandas()
    xs = attributes(df)
    assert len(live) == len(batch) and np.array_equal(live.cached, batch.cached)
    assert np.allclose(live[xs], batch[xs], rtol=1e-6)


def stream_input(spark, sf_dir):
    from streamfill.sources.tables import DAY, HOUR, bucket_of

    df = fixture(spark, sf_dir, "ev").where("window_id < 19736")
    xs = attributes(df)
    rows = df.withColumn("ts", F.timestamp_seconds(bucket_of(F.col("inst_id")) * HOUR))
    last = rows.agg(F.max("window_id").alias("w")).select((F.col("w") + 2).alias("window_id"), F.lit("end").alias("stream_id"), F.lit(0).cast("long").alias("inst_id"), *(F.lit(None).cast("double").alias(c) for c in xs), F.timestamp_seconds((F.col("w") + 2) * DAY).alias("ts"))
    scaler = fill.Scaler.fit(df)
    return rows, last, (scaler.mean, scaler.scale), DAY


def test_a_stopped_stream_goes_on_the_same(spark, sf_dir, tmp_path):
    from streamfill.streaming.live import live

    rows, last, scale, day = stream_input(spark, sf_dir)
    windows_of = sorted(r.window_id for r in rows.select("window_id").distinct().collect())
    half = windows_of[len(windows_of) // 2]

    def run(folder, first, then):
        for part in (first, then):
            if part is not None:
                part.coalesce(1).write.mode("append").parquet(f"{folder}/in")
                source = spark.readStream.schema(rows.schema).parquet(f"{folder}/in")
                q = live(source, Options(mode="dual_carry", epochs=3, eta=0.25), day, scale).writeStream.format("parquet").option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).start()
                q.awaitTermination()
        return spark.read.parquet(f"{folder}/out").where("stream_id <> 'end'").orderBy("inst_id").toPandas()

    whole = run(f"{tmp_path}/a", rows.unionByName(last), None)
    cut = run(f"{tmp_path}/b", rows.where(F.col("window_id") <= half), rows.where(F.col("window_id") > half).unionByName(last))
    assert len(whole) == rows.count() and whole.equals(cut)


def test_batches_run_again_give_the_same(spark, sf_dir, tmp_path):
    from streamfill.streaming.live import by_batches

    rows, _, scale, _ = stream_input(spark, sf_dir)
    rows = rows.drop("ts").where("window_id < 19733")
    days = sorted(r.window_id for r in rows.select("window_id").distinct().collect())
    o = Options(mode="dual_carry", epochs=3, eta=0.25)

    def run(folder, parts):
        for part in parts:
            for d in part:
                rows.where(F.col("window_id") == d).coalesce(1).write.mode("append").parquet(f"{folder}/in")
            source = spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(f"{folder}/in")
            by_batches(source, f"{folder}/out", o, scale, f"{folder}/state", shards=2).awaitTermination()
        return spark.read.parquet(f"{folder}/out").drop("batch").orderBy("window_id", "inst_id").toPandas()

    whole, cut = run(f"{tmp_path}/a", [days]), run(f"{tmp_path}/b", [days[:2], days[2:]])
    assert len(whole) == rows.count() and whole.cached.max() > 0 and whole.equals(cut)


def test_threshold_graph_loses_nothing(spark, sf_dir):
    df = fixture(spark, sf_dir, "lowrank")
    want = graph.pairs(df).where("dist < 0.01").select("window_id", "src", "dst")
    got = graph.threshold(df, 0.1).select("window_id", "src", "dst")
    assert want.count() and want.exceptAll(got).count() == 0 and got.exceptAll(want).count() == 0


def test_approximate_neighbours(spark, sf_dir):
    assert workloads.approximate_recall(spark, sf_dir).toPandas().recall.min() >= 0.9


def test_split_bounds_windows(spark, sf_dir):
    df = windows.split(fixture(spark, sf_dir, "doc"), 60)
    n = df.groupBy("window_id", "sub").count().toPandas()
    assert n["count"].sum() == 200 and n["count"].max() < 100


def test_schema_takes_any_number(spark):
    df = spark.createDataFrame([(1, 5, True, float("nan"), 2.5), (1, 7, False, float("inf"), None)], "s int, t int, a boolean, b double, c float")
    out = InstanceSchema("s", TimeAxis("t", 5, "index"), ("a", "b", "c")).chunks(df).orderBy("x0").collect()
    assert [(r.window_id, r.x0, r.x1, r.x2) for r in out] == [(1, 0.0, None, None), (1, 1.0, None, 2.5)]


def test_joins(spark):
    a = spark.createDataFrame([(1, 10), (1, 20), (2, 5)], "k int, t long")
    b = spark.createDataFrame([(1, 12, 7), (1, 3, 5)], "k int, t long, v int")
    assert {(r.k, r.t, r.v) for r in relational.asof(a, b, "k", "v").collect()} == {(1, 10, 5), (1, 20, 7), (2, 5, None)}
    assert {(r.t, r.r_t) for r in relational.interval_join(a, b, 2).collect()} == {(10, 12), (5, 3)}


def test_state_and_window_sinks(spark, sf_dir, tmp_path):
    from streamfill.sources import sinks

    df = spark.createDataFrame([(1, 2.0), (2, 3.0)], "window_id int, v double")
    sinks.write_windows(df, f"{tmp_path}/w")
    sinks.write_windows(df.where("window_id = 2").selectExpr("window_id", "v + 1 as v"), f"{tmp_path}/w")
    assert {(r.window_id, r.v) for r in spark.read.parquet(f"{tmp_path}/w").collect()} == {(1, 2.0), (2, 4.0)}
    sinks.save_state(df, f"{tmp_path}/s")
    assert sinks.load_state(spark, f"{tmp_path}/s", 1).count() == 1


def test_entry_is_importable():
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries()) and len(e.queries()) > 90


def test_split_by_cell_bounds_large_windows(spark):
    for value in ("id % 977", "floor(id / 3000)", "1"):
        df = spark.range(9000).selectExpr("1L AS window_id", "id AS inst_id", f"CAST({value} AS DOUBLE) AS x0")
        parts = windows.split(df, 20, by="cell").groupBy("sub").agg({"x0": "min", "*": "count"}).toPandas()
        top = windows.split(df, 20, by="cell").groupBy("sub").agg({"x0": "max"}).toPandas().set_index("sub").sort_index()
        low = parts.set_index("sub").sort_index()
        assert parts["count(1)"].sum() == 9000 and parts["count(1)"].max() <= 20
        assert (top["max(x0)"].iloc[:-1].to_numpy() <= low["min(x0)"].iloc[1:].to_numpy()).all()


def test_importance_pairs_masks_not_rows(spark):
    from streamfill.operators import importance

    rows = [(1, i, None if i % 2 else 1.0, None if i % 3 else 2.0) for i in range(60)] + [(2, 7, 1.0, None)]
    df = spark.createDataFrame(rows, "window_id long, inst_id long, x0 double, x1 double")
    seen = {i: {d for d, v in enumerate(x) if v is not None} for w, i, *x in rows if w == 1}
    want = {i: sum(len(a - b) for k, b in seen.items() if k != i) / 59 for i, a in seen.items()}
    plan = importance.pairwise(df)
    assert {r.inst_id: r.phi for r in plan.collect()} == want
    assert "a.inst_id" not in plan._jdf.queryExecution().toString() and "NOT (inst_id" not in plan._jdf.queryExecution().toString()


def copied(spark):
    """Windows of few values and many rows each, a row of zeros, and a row alone."""
    rows = [(w, "s", 100 * w + i, float(i % 3) * 2, float(i % 2)) for w in (1, 2) for i in range(40)] + [(3, "s", 300, 1.0, None)]
    return spark.createDataFrame(rows, "window_id long, stream_id string, inst_id long, x0 double, x1 double")


def test_copies_are_compared_once(spark):
    df = copied(spark).where("window_id < 3")
    assert graph.classes(df, 3).count() == 12
    for metric in ("euclidean", "cosine"):
        all_pairs = graph.pairs(df, metric).toPandas()
        near = all_pairs.sort_values(["window_id", "src", "dist", "dst"]).groupby(["window_id", "src"]).head(5)[["window_id", "src", "dst"]]
        got = graph.nearest(df, 5, metric).toPandas()
        assert set(got[["window_id", "src", "dst"]].itertuples(index=False, name=None)) == set(near.itertuples(index=False, name=None)) and len(got) == len(near)
        want = all_pairs.groupby("window_id").dist.agg(["size", "min", "max"])
        for r in graph.extremes(copied(spark).fillna(0.0), metric).collect():
            w = want.loc[r.window_id]
            assert r.n == w["size"] and abs(r.least - w["min"]) < 1e-12 and abs(r.most - w["max"]) < 1e-12


def test_snapshot_means_are_of_whole_windows(spark):
    df = spark.range(60).selectExpr("id % 2 AS window_id", "'s' AS stream_id", "id AS inst_id", "CASE WHEN id % 3 > 0 THEN CAST(id * id AS DOUBLE) END AS x0")
    want = {r.window_id: r.m for r in df.groupBy("window_id").agg({"x0": "avg"}).withColumnRenamed("avg(x0)", "m").collect()}
    got = snapshot(df, "mean", max_rows=10, scale=False).where("is_imputed[0]").collect()
    assert len(got) == 20 and all(r.x0 == want[r.window_id] for r in got)


def test_snapshot_trains_on_whole_windows(spark):
    from streamfill.plans.impute import impute_window

    rng = np.random.default_rng(3)
    x = rng.normal(size=(20_001, 2))
    x[rng.random(x.shape) < 0.3] = np.nan
    cells = [(1, "s", i, *(None if np.isnan(v) else float(v) for v in r)) for i, r in enumerate(x)]
    df = spark.createDataFrame(cells, "window_id long, stream_id string, inst_id long, x0 double, x1 double")
    got = snapshot(df, "propnet", scale=False, epochs=2).orderBy("inst_id").toPandas()
    assert np.abs(got[["x0", "x1"]].to_numpy() - impute_window(x, Options(epochs=2), (1, 0)).x).max() < 1e-8


def test_links_count_every_row(spark):
    df = copied(spark).fillna(0.0)
    for metric, eps in (("euclidean", 2.1), ("cosine", 0.2), ("cosine", 1.5)):
        below = eps * eps if metric == "euclidean" else eps
        want = graph.pairs(df, metric).where(f"dist < {below}").groupBy("window_id", "src").count().toPandas().set_index(["window_id", "src"])["count"].to_dict()
        least = {}
        rows = df.orderBy("inst_id").collect()
        for r in rows:
            least.setdefault((r.window_id, r.x0, r.x1), r.inst_id)
        got = {(r.window_id, r.inst_id): (r.class_id, r.links) for r in graph.links(df, eps, metric).collect()}
        assert got == {(r.window_id, r.inst_id): (least[r.window_id, r.x0, r.x1], want.get((r.window_id, r.inst_id), 0)) for r in rows}


def test_memory_sink_holds_counts_only(spark, sf_dir, monkeypatch):
    from streamfill.plans import surface
    from streamfill.sources import sinks

    names, made = [], sinks.to_memory
    monkeypatch.setattr(sinks, "to_memory", lambda stream, name, *mode: (names.append(name), made(stream, name, *mode))[1])
    n = spark.read.parquet(f"{sf_dir}/events.parquet").count()
    assert {(r.sink, r.n) for r in surface.stream_sinks(spark, sf_dir).collect()} == {("memory", n), ("foreach_batch", n)}
    assert spark.table(names[0]).count() == 1
