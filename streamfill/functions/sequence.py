"""Sequence baselines, re-implemented from their public descriptions: a bidirectional recurrent imputer with time
decay, and one of two self-attention blocks whose diagonal is masked. The streams of a window are the batch."""

from __future__ import annotations

import numpy as np

from streamfill.functions.autodiff import Adam, Var, absolute, concat, exp, masked_mae, relu, sigmoid, softmax, tanh


def folded(x: np.ndarray, streams: np.ndarray, times: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(values, gaps, place of each row): streams x steps x D with NaN, times padded by their last."""
    _, owner = np.unique(streams, return_inverse=True)
    order = np.lexsort((times, owner))
    start = np.concatenate([[0], np.flatnonzero(np.diff(owner[order])) + 1])
    step = np.arange(len(x)) - np.repeat(start, np.diff([*start, len(x)]))
    steps = int(step.max(initial=0)) + 1
    cube, at = np.full((owner.max(initial=0) + 1, steps, x.shape[1]), np.nan), np.zeros((owner.max(initial=0) + 1, steps))
    cube[owner[order], step], at[owner[order], step] = x[order], times[order]
    place = np.empty((len(x), 2), np.int64)
    place[order] = np.column_stack([owner[order], step])
    return cube, at, place


def since_seen(seen: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Time since each attribute was last observed, in mean steps."""
    gap = np.maximum(np.diff(at, axis=1, prepend=at[:, :1]), 0)
    unit = gap[gap > 0].mean() if (gap > 0).any() else 1.0
    out = np.zeros(seen.shape)
    for t in range(1, seen.shape[1]):
        out[:, t] = gap[:, t, None] / unit + np.where(seen[:, t - 1], 0.0, out[:, t - 1])
    return np.minimum(out, 1e3)


def _drawn(rng: np.random.Generator, a: int, b: int) -> np.ndarray:
    return rng.uniform(-1, 1, (a, b)) * np.sqrt(6 / (a + b))


def brits_weights(d: int, hidden: int, rng: np.random.Generator) -> dict[str, np.ndarray]:
    theta = {}
    for way in ("f", "b"):
        theta |= {f"{way}.{k}": _drawn(rng, *s) for k, s in {"decay_h": (d, hidden), "decay_x": (d, d), "hist": (hidden, d), "feat": (d, d), "mix": (2 * d, d), "in": (2 * d, hidden), "rec": (hidden, hidden)}.items()}
        theta |= {f"{way}.{k}": np.zeros((1, n)) for k, n in {"bh": hidden, "bx": d, "bo": d, "bf": d, "bm": d, "bi": hidden}.items()}
    return theta


#: Steps of streams, padded, whose tape is held at a time.
STRIP = 4096


def _strips(cube: np.ndarray) -> list[slice]:
    """Streams dealt so that a part has about STRIP steps. A loss is a sum over streams, so gradients of parts add up."""
    many = max(1, STRIP // max(1, cube.shape[1]))
    return [slice(a, a + many) for a in range(0, len(cube), many)] or [slice(0, 0)]


def _run(w: dict[str, Var], way: str, x: np.ndarray, seen: np.ndarray, delta: np.ndarray, by: np.ndarray) -> tuple[list[Var], Var]:
    """by: the cells observed at each step, over all streams."""
    p = lambda k: w[f"{way}.{k}"]
    d = x.shape[2]
    no_self = 1.0 - np.eye(d)
    h, out, loss = Var(np.zeros((len(x), p("rec").shape[0]))), [], Var(0.0)
    for t in range(x.shape[1]):
        m, v, gap = seen[:, t].astype(float), x[:, t], Var(delta[:, t])
        h = h * exp(-relu(gap @ p("decay_h") + p("bh")))
        history = h @ p("hist") + p("bo")
        own = history * (1 - m) + v * m
        feature = own @ (p("feat") * no_self) + p("bf")
        fade = exp(-relu(gap @ p("decay_x") + p("bx")))
        mix = sigmoid(concat([fade, Var(m)]) @ p("mix") + p("bm"))
        both = mix * feature + (1.0 - mix) * history
        loss = loss + masked_mae(history, v, m, by[t]) + masked_mae(feature, v, m, by[t]) + masked_mae(both, v, m, by[t])
        filled = both * (1 - m) + v * m
        h = tanh(concat([filled, Var(m)]) @ p("in") + h @ p("rec") + p("bi"))
        out.append(both)
    return out, loss


def brits(x: np.ndarray, streams: np.ndarray, times: np.ndarray, hidden: int = 32, epochs: int = 30, lr: float = 0.01, seed: int = 0) -> tuple[np.ndarray, int]:
    """(filled rows, bytes of the weights as 32-bit numbers)."""
    cube, at, place = folded(x, streams, times)
    seen = ~np.isnan(cube)
    v = np.where(seen, cube, 0.0)
    ways = {"f": (v, seen, since_seen(seen, at)), "b": (v[:, ::-1], seen[:, ::-1], since_seen(seen[:, ::-1], -at[:, ::-1]))}
    theta, optimiser = brits_weights(x.shape[1], hidden, np.random.default_rng(seed)), Adam(lr)
    by, mean = {k: way[1].sum(axis=(0, 2)) for k, way in ways.items()}, np.empty(cube.shape)
    for epoch in range(epochs + 1):
        w = {k: Var(a) for k, a in theta.items()}
        for some in _strips(cube):
            (f, lf), (b, lb) = (_run(w, k, *(a[some] for a in ways[k]), by[k]) for k in ("f", "b"))
            b = b[::-1]
            if epoch == epochs:
                mean[some] = np.stack([(p.data + q.data) / 2 for p, q in zip(f, b, strict=True)], axis=1)
                continue
            agree = sum((absolute(p - q).sum() for p, q in zip(f, b, strict=True)), Var(0.0)) * (0.1 / max(v.size, 1))
            (lf + lb + agree).backward()
        if epoch < epochs:
            theta = optimiser.update(theta, {k: a.grad for k, a in w.items() if a.grad is not None})
    return np.where(np.isnan(x), mean[place[:, 0], place[:, 1]], x), sum(a.size for a in theta.values()) * 4


def saits_weights(d: int, model: int, rng: np.random.Generator) -> dict[str, np.ndarray]:
    theta = {}
    for b in ("1", "2"):
        theta |= {f"{b}.{k}": _drawn(rng, *s) for k, s in {"embed": (2 * d, model), "q": (model, model), "k": (model, model), "v": (model, model), "o": (model, model), "ff": (model, 2 * model), "gg": (2 * model, model), "out": (model, d)}.items()}
        theta |= {f"{b}.be": np.zeros((1, model)), f"{b}.bo": np.zeros((1, d)), f"{b}.bf": np.zeros((1, 2 * model))}
    return theta | {"mix": _drawn(rng, 2 * d, d), "bm": np.zeros((1, d))}


def _block(w: dict[str, Var], b: str, x: Var, m: np.ndarray, code: np.ndarray, blocked: np.ndarray, heads: int) -> Var:
    p = lambda k: w[f"{b}.{k}"]
    e = concat([x, Var(m)]) @ p("embed") + p("be") + code
    size = e.shape[-1] // heads
    parts = []
    for h in range(heads):
        cut = (..., slice(h * size, (h + 1) * size))
        q, k, v = (e @ p("q"))[cut], (e @ p("k"))[cut], (e @ p("v"))[cut]
        parts.append(softmax(q @ k.turned() * size**-0.5 + blocked) @ v)
    e = e + concat(parts) @ p("o")
    e = e + relu(e @ p("ff") + p("bf")) @ p("gg")
    return e @ p("out") + p("bo")


def saits(x: np.ndarray, streams: np.ndarray, times: np.ndarray, model: int = 32, heads: int = 2, epochs: int = 30, lr: float = 0.005, hide: float = 0.2, seed: int = 0) -> tuple[np.ndarray, int]:
    """(filled rows, bytes of the weights as 32-bit numbers)."""
    cube, _, place = folded(x, streams, times)
    real = ~np.isnan(cube)
    v, (_, steps, d) = np.where(real, cube, 0.0), cube.shape
    pos = np.arange(steps)[:, None] / 10000 ** (np.arange(model)[None, :] // 2 * 2 / model)
    code = np.where(np.arange(model) % 2 == 0, np.sin(pos), np.cos(pos))
    itself = np.where(np.eye(steps) > 0, -1e9, 0.0) if steps > 1 else np.zeros((1, 1))
    empty, last = np.where(real.any(axis=2), 0.0, -1e8)[:, None, :], np.empty(cube.shape)
    rng = np.random.default_rng(seed)
    theta, optimiser = saits_weights(d, model, rng), Adam(lr)
    for epoch in range(epochs + 1):
        w = {k: Var(a) for k, a in theta.items()}
        hidden = real & (rng.random(real.shape) < (hide if epoch < epochs else 0))
        m = (real & ~hidden).astype(float)
        by, by_hidden = m.sum(), float(hidden.sum())
        for some in _strips(cube):
            vs, ms, rows = v[some], m[some], itself + empty[some]
            first = _block(w, "1", Var(vs * ms), ms, code, rows, heads)
            again = first * (1 - ms) + vs * ms
            second = _block(w, "2", again, ms, code, rows, heads)
            share = sigmoid(concat([second, Var(ms)]) @ w["mix"] + w["bm"])
            made = share * second + (1.0 - share) * first
            if epoch == epochs:
                last[some] = made.data
                continue
            loss = masked_mae(first, vs, ms, by) + masked_mae(second, vs, ms, by) + masked_mae(made, vs, ms, by) + masked_mae(made, vs, hidden[some].astype(float), by_hidden)
            loss.backward()
        if epoch < epochs:
            theta = optimiser.update(theta, {k: a.grad for k, a in w.items() if a.grad is not None})
    return np.where(np.isnan(x), last[place[:, 0], place[:, 1]], x), sum(a.size for a in theta.values()) * 4
