"""What the registered workloads ask for; nothing is run."""

import numpy as np
import pytest

from streamfill.plans import workloads
from streamfill.plans.continuous import worth_keeping
from streamfill.plans.impute import Options


@pytest.fixture
def asked(monkeypatch):
    """(labels, options) of every sweep that a workload asks for."""
    out = []
    for owner, name in ((workloads, "fixture"), (workloads, "union"), (workloads.masks, "keep_streams"), (workloads.masks, "irregular")):
        monkeypatch.setattr(owner, name, lambda *a, **b: None)
    monkeypatch.setattr(workloads, "kept", lambda spark, sf_dir, name, make: make())
    monkeypatch.setattr(workloads, "sweep", lambda df, rate, options, labels, *a, **b: out.extend((labels[k] | {"rate": rate}, options[k]) for k in options))
    return out


def test_caches_are_whole(asked):
    workloads.w6_continuous(None, "")
    assert len(asked) == 12 and all(o.max_cache is None for _, o in asked)
    assert len(worth_keeping(np.ones((6000, 3)), Options(eta=0.0))) == 6000


def test_training_and_grids_are_whole(asked):
    for name in ("w1_effectiveness", "w1_effectiveness_sparse", "w1_effectiveness_dense", "w1_effectiveness_wide", "w4_window_length", "w5_stream_ratio", "w6_continuous", "w7_irregular", "w9_similarity", "w10_neighbours", "w11_layers", "w12_modules", "w13_importance_threshold", "w14_losses", "w15_without_bound", "w16_transfer", "w19_hyperparameters"):
        workloads.QUERIES[name](None, "")
    assert all((o.epochs, o.seq_epochs, o.patience) == (200, 30, None) for _, o in asked)
    met = {(lab.get("fixture"), lab["rate"], lab["method"]) for lab, _ in asked if set(lab) == {"fixture", "rate", "method"}}
    assert met >= {(n, r, m) for n in ("ev", "doc", "lowrank", "li", "emb") for r in workloads.RATES[n] for m in workloads.METHODS}
    count = lambda key, n: len({lab[key] for lab, _ in asked if key in lab and lab.get("fixture") == n})
    assert [count("length", n) for n in ("ev", "li", "emb")] == [6, 5, 5] and [count("ratio", n) for n in ("ev", "li")] == [11, 11]
    assert {lab["fixture"] for lab, _ in asked if "mode" in lab and "fixture" in lab} == {"ev", "li"}


def test_memory_is_weighed_over_the_windows_of_the_tables(spark, sf_dir):
    rows = workloads.w3_memory(spark, sf_dir).collect()
    n = {name: workloads.fixture(spark, sf_dir, name).select("window_id").distinct().count() for name in ("ev", "doc", "li", "lowrank", "emb")}
    assert len(rows) == 15 and {(r.fixture, r.n_windows) for r in rows} == set(n.items())
    assert all(abs(r.all_mb - r.model_mb * r.n_windows) < 1e-9 for r in rows)


def test_chains_have_the_cores_of_their_executor(spark, monkeypatch):
    from types import SimpleNamespace

    from streamfill.plans.groups import idle_cores

    assert [idle_cores(spark, n) for n in (1, 2, 3, 9)] == [4, 2, 1, 1]
    for master, given, want in (("local-cluster[3,2,3000]", None, 2), ("yarn", "5", 5), ("yarn", None, 1)):
        context = SimpleNamespace(master=master, defaultParallelism=6, getConf=lambda given=given: SimpleNamespace(get=lambda key: given))
        assert idle_cores(SimpleNamespace(sparkContext=context), 1) == want
    asked, run = [], workloads.continuous.run
    monkeypatch.setattr(workloads.continuous, "run", lambda *a, **more: (asked.append(more["cores"]), run(*a, **more))[1])
    for name in ("model_carry", "dual_carry"):
        workloads.QUERIES[name](spark, "/root/testdata/sf0.001")
    assert asked == [4, 4]
