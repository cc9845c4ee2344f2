"""The distributed trainer against the kernel on one window."""

import numpy as np
from pyspark.sql import functions as F

from streamfill.functions import kernels, nets
from streamfill.operators import masks
from streamfill.plans.graph_engine import fit_impute
from streamfill.plans.impute import Options, seeded
from streamfill.schema import attributes
from streamfill.sources.tables import fixture


def test_blocks_equal_one_block(spark, sf_dir, monkeypatch):
    """Rows dealt over several blocks, and over more blocks than some rows fall in, train as in one; an epoch is one job."""
    from streamfill.plans import graph_engine

    chunk = masks.remove_cells(fixture(spark, sf_dir, "lowrank").where("window_id = 0"), 0.3, 3)[0].where("inst_id < 60").localCheckpoint()
    runs, jobs = [], []
    for rows, epochs in ((2048, 2), (15, 2), (8, 2), (15, 6)):
        monkeypatch.setattr(graph_engine, "ROWS", rows)
        spark.sparkContext.setJobGroup(f"blocks {rows} {epochs}", "")
        out, theta, trace = fit_impute(chunk, Options(epochs=epochs, beta=0.1, k=5, width=8))
        jobs.append(len(spark.sparkContext.statusTracker().getJobIdsForGroup(f"blocks {rows} {epochs}")))
        runs.append((trace, theta, out.orderBy("inst_id").toPandas().iloc[:, 3:].to_numpy()))
    for trace, theta, out in runs[1:3]:
        assert np.allclose(trace, runs[0][0]) and np.allclose(out, runs[0][2])
        assert all(np.allclose(theta[k], runs[0][1][k]) for k in theta)
    assert jobs[3] - jobs[1] <= 4


def test_equals_the_kernel(spark, sf_dir):
    o = Options(epochs=3, beta=0.1, k=5, width=8)
    chunk = masks.remove_cells(fixture(spark, sf_dir, "lowrank").where("window_id = 0"), 0.3, 3)[0]
    out, theta, trace = fit_impute(chunk, o)
    xs = attributes(chunk)
    x = chunk.orderBy("inst_id").toPandas()[xs].to_numpy()
    kept = masks.remove_cells(chunk, o.beta, o.seed)[0].orderBy("inst_id").toPandas()[xs].to_numpy()
    seen, held = ~np.isnan(kept), ~np.isnan(x) & np.isnan(kept)
    x0 = kernels.mean_filled(kept)
    shape = o.shape(len(xs))
    rows, best, want = nets.fit(x0, seen.astype(float), np.nan_to_num(x), held, kernels.build_graph(x0, 5), shape, o.training(), nets.init(shape, seeded(0)))
    assert np.allclose(trace, want)
    assert all(np.allclose(theta[k], best[k]) for k in best)
    got = out.orderBy(F.col("inst_id")).toPandas()[xs].to_numpy()
    assert np.allclose(got, np.where(np.isnan(x), rows, x))
