"""Worked examples, invariants and exact values of the methods."""

import numpy as np
import pytest

from streamfill.functions import kernels as K
from streamfill.functions import nets as N
from streamfill.functions import sequence
from streamfill.functions.autodiff import Adam, Var, masked_mse
from streamfill.plans.continuous import Chain, next_state, worth_keeping
from streamfill.plans.impute import METHODS, Options, impute_window

NAN = np.nan


def gappy(n=80, d=6, rate=0.4, seed=0):
    rng = np.random.default_rng(seed)
    x = rng.normal(size=(n, 2)) @ rng.normal(size=(2, d))
    return x, np.where(rng.random(x.shape) < rate, NAN, x)


def test_first_example():
    x = np.array([[NAN, 5, 6], [8, 5, 3], [3, 2, 1]])
    g = K.Graph(3, np.array([0, 0, 1]), np.array([1, 2, 2]))
    assert K.feature_propagation(x, g, 1)[0].tolist() == [5.5, 5, 6]
    c = np.where((g.src == 0) & (g.dst == 1), 0.8, np.where(g.src == 0, 0.2, 0.0))
    assert g.gather(c, K.mean_filled(x))[0].tolist() == pytest.approx([7.0, 4.4, 2.6])


def test_second_example():
    x = np.array([[NAN, NAN, 4], [12, NAN, 6]])
    assert (K.importance(~np.isnan(x)) * 2).tolist() == [0, 1]
    assert (K.importance_gram(~np.isnan(x)) * 2).tolist() == [0, 1]
    assert worth_keeping(x, Options(eta=0.5)).tolist() == [1] and not len(worth_keeping(x, Options(eta=0.6)))
    assert 0.2 * 8 + 0.8 * 12 == pytest.approx(11.2)


@pytest.mark.parametrize("n,d", [(1, 3), (2, 1), (50, 4), (300, 11)])
def test_importance_forms_agree_and_stay_in_range(n, d):
    seen = np.random.default_rng(n).random((n, d)) < 0.5
    seen[~seen.any(axis=1), 0] = True
    phi = K.importance(seen)
    if n > 1:
        assert np.abs(phi - K.importance_gram(seen)).max() < 1e-12
        m = seen.astype(int)
        pairs = [[(m[i] * (1 - m[k])).sum() for k in range(n) if k != i] for i in range(n)]
        assert phi == pytest.approx(np.mean(pairs, axis=1) / max(1, d - 1))
    assert phi.min() >= 0 and (phi.max() <= 1 + 1e-12 or d == 1)


def test_range_needs_an_observed_cell():
    assert K.importance(np.array([[1, 1, 1], [0, 0, 0]], bool)).max() == 1.5


@pytest.mark.parametrize("metric", ["euclidean", "cosine"])
def test_nearest_is_exact(metric):
    x = np.random.default_rng(1).normal(size=(60, 5))
    x[7] = x[3]
    d = K.distances(x, x, metric)
    for i, row in enumerate(K.nearest(x, 4, metric)):
        order = [k for k in np.lexsort((np.arange(60), d[i])) if k != i]
        assert row.tolist() == order[:4]


def test_graph_is_symmetric_without_loops():
    g = K.build_graph(np.random.default_rng(2).normal(size=(40, 3)), 5)
    edges = set(zip(g.src.tolist(), g.dst.tolist(), strict=True))
    assert all((b, a) in edges and a != b for a, b in edges) and g.degree.min() >= 5
    h = np.random.default_rng(3).normal(size=(40, 2))
    for how in ("sym", "row"):
        forward, back = g.operator(how)
        assert np.allclose(forward(h), g.gather(g.weights(how), h)) and np.allclose(back(h), g.gather(g.weights(how)[g.back], h))


def test_propagation_lowers_energy_and_forgets_its_start():
    _, x = gappy()
    g = K.build_graph(K.mean_filled(x))
    w = g.weights("sym")
    s = np.zeros((g.n, g.n))
    s[g.src, g.dst] = w
    last = np.inf
    for n in range(1, 15):
        y = K.feature_propagation(x, g, n)
        e = np.trace(y.T @ (np.eye(g.n) - s) @ y)
        assert e <= last + 1e-9
        last = e
        assert np.array_equal(y[~np.isnan(x)], x[~np.isnan(x)])
    far = K.feature_propagation(x, g, 3000)
    assert np.abs(K.feature_propagation(far * 0 + np.where(np.isnan(x), NAN, x), g, 3000) - far).max() < 1e-6


def test_propagation_is_a_message_step():
    x, _ = gappy()
    g = K.build_graph(x)
    z = g.operator("sym")[0](x) @ np.eye(6) @ np.eye(6)
    shape = N.Shape(6, width=6, layers=1, module="gcn", bound=False, act=False)
    theta = {"msg0.near": np.eye(6), "msg0.bias": np.zeros((1, 6)), "rec0.out": np.eye(6), "rec0.bias": np.zeros((1, 6))}
    _, h = N.forward({k: Var(v) for k, v in theta.items()}, x, np.ones_like(x), shape, g)
    assert np.allclose(h.data, z)


def test_attention_sums_to_one():
    from streamfill.functions.autodiff import edge_softmax

    g = K.build_graph(np.random.default_rng(4).normal(size=(30, 3)), 4)
    c = edge_softmax(Var(np.random.default_rng(5).normal(size=len(g.src))), g.starts, g.owner)
    assert np.allclose(np.bincount(g.src, c.data), 1)


@pytest.mark.parametrize("module", ["sage", "gcn", "gat"])
def test_gradients(module):
    rng = np.random.default_rng(6)
    shape, x, seen = N.Shape(4, width=6, module=module), rng.normal(size=(15, 4)), (rng.random((15, 4)) < 0.7).astype(float)
    g, theta = K.build_graph(x, 3), N.init(N.Shape(4, width=6, module=module), rng)

    def loss(t):
        w = {k: Var(v) for k, v in t.items()}
        made, _ = N.forward(w, x, seen, shape, g)
        return masked_mse(made[0], x, seen, 60.0) + masked_mse(made[1], x, seen, 60.0), w

    value, w = loss(theta)
    value.backward()
    for k, v in theta.items():
        at = tuple(int(rng.integers(n)) for n in v.shape)
        up, down = ({**theta, k: v.copy()} for _ in range(2))
        up[k][at] += 1e-6
        down[k][at] -= 1e-6
        assert w[k].grad[at] == pytest.approx((loss(up)[0].data - loss(down)[0].data) / 2e-6, rel=1e-4, abs=1e-8)


def test_the_best_epoch_is_returned_with_its_weights():
    _, x = gappy()
    rng, seen = np.random.default_rng(7), ~np.isnan(x)
    held = N.hold_out(seen, 0.1, rng)
    left = (seen & ~held).astype(float)
    x0 = K.mean_filled(np.where(held, NAN, x))
    g, shape = K.build_graph(x0), N.Shape(6)
    rows, theta, trace = N.fit(x0, left, np.where(seen, x, 0), held, g, shape, N.Training(epochs=30), N.init(shape, rng))
    made, h = N.forward({k: Var(v) for k, v in theta.items()}, x0, left, shape, g)
    assert np.array_equal(h.data, rows)
    assert np.abs(made[-1].data - x)[held].mean() == min(trace)


@pytest.mark.parametrize("method", METHODS)
@pytest.mark.parametrize("x", [np.full((3, 2), NAN), np.array([[1.0, NAN]]), np.zeros((0, 3)), np.array([[1.0, NAN], [1.0, 2.0], [1.0, NAN]]), gappy()[1]], ids=["missing", "one", "empty", "constant", "usual"])
def test_every_method_fills_everything(method, x):
    if not len(x):
        return
    out = impute_window(x, Options(method=method, epochs=5, seq_epochs=2))
    assert np.isfinite(out.x).all() and np.array_equal(out.x[~np.isnan(x)], x[~np.isnan(x)])


def test_low_rank_data_is_recovered():
    x, gaps = gappy(150, 10)
    hidden = np.isnan(gaps)
    error = lambda y: np.abs(y - x)[hidden].mean() / np.abs(x)[hidden].mean()
    mean = error(K.mean_filled(gaps))
    assert error(K.mf(gaps, 2, 500)) < 0.1 * mean and error(K.mice(gaps)) < 0.3 * mean
    assert error(impute_window(gaps, Options(epochs=200)).x) < 0.9 * mean
    for m in ("brits", "saits", "knn", "fp"):
        assert error(impute_window(gaps, Options(method=m, seq_epochs=40)).x) < mean


def test_what_goes_to_the_next_window():
    o = Options(mode="dual_carry", epochs=5, eta=0.2)
    chain, (_, x) = Chain(o), gappy()
    out, cached = chain.step(0, x, np.zeros(80), np.arange(80))
    assert cached == 0 and all(k.startswith("msg") for k in chain.theta)
    assert all(np.array_equal(chain.theta[k], out.theta[k]) for k in chain.theta)
    kept = len(chain.cache[0])
    out, cached = chain.step(1, x[:10], np.zeros(10), np.arange(80, 90))
    assert cached == kept and len(out.x) == 10
    assert next_state(out.theta, Options(update="none")) is None and next_state(out.theta, Options(update="all")) is out.theta
    assert len(worth_keeping(x, Options(eta=0.0, max_cache=7))) == 7


def test_frozen_messages_stay():
    _, x = gappy()
    theta = N.init(N.Shape(6), np.random.default_rng(8))
    carried = {k: v for k, v in theta.items() if k.startswith("msg")}
    out = impute_window(x, Options(epochs=10, update="frozen"), theta=carried)
    assert all(np.array_equal(out.theta[k], v) for k, v in carried.items())


def test_decoupled_decay():
    step = Adam(0.1, 0.5, decoupled=True).update({"w": np.ones(2)}, {"w": np.zeros(2)})
    assert step["w"] == pytest.approx(0.95)


def test_nearest_compares_few_rows_and_loses_none(monkeypatch):
    rng, compared = np.random.default_rng(8), []
    gaps = K._gaps
    monkeypatch.setattr(K, "_gaps", lambda a, b: compared.append(len(a) * len(b)) or gaps(a, b))

    def plain(x, k):
        d = ((x[:, None] - x[None]) ** 2).sum(axis=2)
        np.fill_diagonal(d, np.inf)
        return np.array([np.lexsort((np.arange(len(x)), row))[:k] for row in d])

    for n, high in ((1, 9), (2, 9), (30, 2), (700, 3), (1200, 400), (1500, 12)):
        x = np.where(rng.random((n, 4)) < 0.4, rng.integers(0, high, (n, 4)), 5.0)
        for k in (1, 10):
            assert np.array_equal(K.nearest(x, k), plain(x, min(k, n - 1)))
    sparse = np.where(rng.random((20_000, 5)) < 0.2, rng.random((20_000, 5)), 0.5)
    for x, share in ((sparse, 5), (np.tile(sparse[:500], (40, 1)), 1000)):
        compared.clear()
        K.nearest(x, 10)
        assert sum(compared) < len(x) ** 2 / share


def test_sums_over_neighbours():
    rng = np.random.default_rng(9)
    n = 900
    hub = np.concatenate([np.zeros(n - 2, int), rng.integers(1, n - 1, 4 * n)])  # one row is near all, and one near none
    g = K.Graph(n, hub, np.concatenate([np.arange(1, n - 1), rng.integers(1, n - 1, 4 * n)]))
    h = rng.normal(size=(n, 3))
    assert np.allclose(g.summed(h), g.gather(np.ones(len(g.src)), h)) and not g.summed(h)[n - 1].any()


@pytest.mark.parametrize("more", [{}, {"module": "gcn"}, {"layers": 3}, {"layers": 1}, {"bound": False}, {"act": False}, {"tie": True}])
def test_training_by_hand_equals_the_tape(more, monkeypatch):
    rng = np.random.default_rng(10)
    x = np.where(rng.random((600, 4)) < 0.4, rng.normal(size=(600, 4)), np.nan)
    seen = ~np.isnan(x)
    held = N.hold_out(seen, 0.2, rng)
    base, left, shape = K.mean_filled(np.where(held, np.nan, x)), (seen & ~held).astype(float), N.Shape(4, **more)
    graph, start, made = K.build_graph(base, 5), N.init(shape, rng), []
    monkeypatch.setattr(N, "STRIP", 256)
    for way in (N._by_hand, N._taped):
        monkeypatch.setattr(N, "_by_hand", way)
        made.append([N.fit(base, left, np.nan_to_num(x), held, graph, shape, t, start) for t in (N.Training(15), N.Training(15, norm="seen", lams=(0.5, 2.0), frozen=True, patience=4))])
    for (a, a_theta, a_trace), (b, b_theta, b_trace) in zip(*made, strict=True):
        assert np.allclose(a, b) and np.allclose(a_trace, b_trace) and all(np.allclose(a_theta[k], b_theta[k]) for k in b_theta)


@pytest.mark.parametrize("module", ["sage", "gcn"])
def test_several_cores_train_to_the_same_bits(module):
    """They share the work of one chain's window, leave no process behind, and do not outlive one that fails."""
    import os

    rng = np.random.default_rng(11)
    x = np.where(rng.random((7000, 3)) < 0.5, rng.normal(size=(7000, 3)), NAN)
    o, places, pids = Options(mode="dual_carry", module=module, layers=3, epochs=6, eta=0.1), np.arange(7000), []
    part = K.Team.start

    def counted(team):
        part(team)
        pids.extend(team.others)

    with pytest.MonkeyPatch.context() as m:
        m.setattr(K.Team, "start", counted)
        outs = []
        for cores in (1, 3):
            chain = Chain(o, cores=cores)
            outs.append([chain.step(w, x[w * 3000 : w * 3000 + 4000 + w * 2000], places[: 4000 + w * 2000] % 9, places[: 4000 + w * 2000])[0] for w in range(2)])
    for a, b in zip(*outs, strict=True):
        assert np.array_equal(a.x, b.x) and a.trace == b.trace and all(np.array_equal(a.theta[k], b.theta[k]) for k in b.theta)
    assert len(pids) >= 2
    for pid in pids:
        with pytest.raises(ProcessLookupError):
            os.kill(pid, 0)

    def broken(s):
        if team.member:
            raise ValueError
        done.append(s)

    done = []
    with pytest.raises(RuntimeError, match="has ended"), K.Team(2, 10) as team:
        team.start()
        team.each(broken, team.strips(40))
    assert [s.start for s in done] == [0, 20]


def test_sequence_baselines_by_strips(monkeypatch):
    """Strips of streams give what the whole gives, and the tape of a large window stays small."""
    import tracemalloc

    rng = np.random.default_rng(4)
    streams = np.repeat(np.arange(700), rng.integers(1, 8, 700))
    x = np.where(rng.random((len(streams), 5)) < 0.5, np.nan, rng.normal(size=(len(streams), 5)))
    for method in (sequence.brits, sequence.saits):
        whole, peaks = [], []
        for strip in (1 << 30, 140, 256):
            monkeypatch.setattr(sequence, "STRIP", strip)
            tracemalloc.start()
            whole.append(method(x, streams, np.arange(len(x)), epochs=3)[0])
            peaks.append(tracemalloc.get_traced_memory()[1])
            tracemalloc.stop()
        assert np.allclose(whole[0], whole[1], atol=1e-9) and np.allclose(whole[0], whole[2], atol=1e-9)
        assert peaks[1] < peaks[0] / 4
