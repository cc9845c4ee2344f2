"""The propagation network: layers of a message module and a reconstruction module with bound observed cells."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from streamfill.functions.autodiff import Adam, Var, concat, edge_softmax, leaky_relu, linear_map, masked_mse, relu
from streamfill.functions.kernels import Graph, Team


@dataclass(frozen=True)
class Shape:
    """module sage, gcn or gat; width of the hidden rows (None: the larger of 32 and 2 D); bound and act can be off."""

    dims: int
    width: int | None = None
    layers: int = 2
    module: str = "sage"
    bound: bool = True
    act: bool = True
    tie: bool = False

    @property
    def hidden(self) -> int:
        return self.width or max(32, 2 * self.dims)


def init(shape: Shape, rng: np.random.Generator) -> dict[str, np.ndarray]:
    d, f = shape.dims, shape.hidden
    drawn = lambda a, b: rng.uniform(-1, 1, (a, b)) * np.sqrt(6 / (a + b))
    theta = {}
    for layer in range(1 if shape.tie else shape.layers):
        if shape.module == "sage":
            theta[f"msg{layer}.self"] = drawn(d, f)
        if shape.module == "gat":
            theta[f"msg{layer}.from"], theta[f"msg{layer}.to"] = drawn(f, 1), drawn(f, 1)
        theta |= {f"msg{layer}.near": drawn(d, f), f"msg{layer}.bias": np.zeros((1, f)), f"rec{layer}.out": drawn(f, d), f"rec{layer}.bias": np.zeros((1, d))}
    return theta


def nbytes(theta: dict[str, np.ndarray], each: int = 4) -> int:
    """Bytes of the weights, as 32-bit numbers unless said otherwise."""
    return sum(v.size for v in theta.values()) * each


def attend(h: Var, theta: dict[str, Var], layer: int, graph: Graph) -> Var:
    """Attention over neighbours: leaky-relu scores of both ends, softmax over each row's edges."""
    z = h @ theta[f"msg{layer}.near"]
    score = leaky_relu((z @ theta[f"msg{layer}.from"])[graph.src, 0] + (z @ theta[f"msg{layer}.to"])[graph.dst, 0])
    c = edge_softmax(score, graph.starts, graph.owner)
    far = z[graph.dst]
    made = np.zeros((graph.n, z.shape[1]))
    made[graph.nodes] = np.add.reduceat(c.data[:, None] * far.data, graph.starts, axis=0)
    return Var(made, (c, far), lambda g: ((g[graph.src] * far.data).sum(axis=1), c.data[:, None] * g[graph.src]))


def message(h: Var, theta: dict[str, Var], layer: int, shape: Shape, graph: Graph, op) -> Var:
    act = relu if shape.act else lambda z: z
    if shape.module == "gat":
        z = attend(h, theta, layer, graph) if len(graph.src) else h @ theta[f"msg{layer}.near"] * 0.0
    else:
        stacked = [theta[f"msg{layer}.{k}"] for k in (("near", "self", "bias") if shape.module == "sage" else ("near", "bias"))]
        ends = [linear_map(h, *op), h] if shape.module == "sage" else [linear_map(h, *op)]
        return act(concat([*ends, Var(np.ones((len(h.data), 1)))]) @ concat(stacked, axis=0))
    return act(z + theta[f"msg{layer}.bias"])


def forward(theta: dict[str, Var], x0: np.ndarray, seen: np.ndarray, shape: Shape, graph: Graph, op=None) -> tuple[list[Var], Var]:
    """(what each layer makes before observed cells are put back, the last rows after)."""
    op = op or graph.operator("row" if shape.module == "sage" else "sym")
    h, made = Var(x0), []
    for layer in range(shape.layers):
        at = 0 if shape.tie else layer
        out = message(h, theta, at, shape, graph, op) @ theta[f"rec{at}.out"] + theta[f"rec{at}.bias"]
        made.append(out)
        h = out * (1.0 - seen) + x0 * seen if shape.bound else out
    return made, h


@dataclass(frozen=True)
class Training:
    epochs: int = 200
    beta: float = 0.05
    lr: float = 0.01
    decay: float = 0.1
    decoupled: bool = False
    lams: tuple[float, ...] = (1.0, 1.0)
    norm: str = "all"
    patience: int | None = None
    frozen: bool = False


def hold_out(seen: np.ndarray, beta: float, rng: np.random.Generator) -> np.ndarray:
    """Which observed cells are kept back to choose the epoch."""
    return seen & (rng.random(seen.shape) < beta)


def _taped(x0: np.ndarray, seen: np.ndarray, shape: Shape, graph: Graph, team: Team, lams: tuple, by: float):
    """A pass: weights to (what the last layer makes, the rows after, a function that gives the loss's gradients)."""
    op = graph.operator("row" if shape.module == "sage" else "sym")

    def passed(theta: dict[str, np.ndarray]):
        weights = {k: Var(v) for k, v in theta.items()}
        made, h = forward(weights, x0, seen, shape, graph, op)

        def back() -> dict[str, np.ndarray]:
            sum((masked_mse(x, x0, seen, by) * lam for x, lam in zip(made, lams, strict=True)), Var(0.0)).backward()
            return {k: w.grad for k, w in weights.items() if w.grad is not None}

        return made[-1].data, h.data, back

    return passed


#: Rows whose hidden layer is held at a time, so that it stays in a core's cache.
STRIP = 1024
#: Rows of a window for which another core pays.
SHARE = 2048


def _by_hand(x0: np.ndarray, seen: np.ndarray, shape: Shape, graph: Graph, team: Team, lams: tuple, by: float):
    """The same for messages that are linear in the rows and their neighbours' sums, by a team. A layer is a product of
    [sums, rows, 1] with its stacked weights, and goes strip by strip. The last layer's way back needs no other rows and
    goes with its way ahead; the hidden units of the others are made again on the way back."""
    n, d = x0.shape
    sage, final, f = shape.module == "sage", shape.layers - 1, shape.hidden
    strips, bound, share = team.strips(n), seen > 0, 1.0 / max(by, 1.0)
    op = graph.operator("row" if sage else "sym", team, d)
    wide = (2 * d if sage else d) + 1
    ends, outs, rows = (team.array((shape.layers, n, k)) for k in (wide, d, d))
    d_in, board = team.array((n, wide - 1)), team.array((shape.layers, len(strips), wide * f + f * d + d))
    first = op[0](x0).copy()

    def stacked(theta: dict[str, np.ndarray], at: int) -> np.ndarray:
        return np.concatenate([theta[f"msg{at}.{k}"] for k in (("near", "self", "bias") if sage else ("near", "bias"))])

    def hidden(c: np.ndarray, w: np.ndarray) -> np.ndarray:
        z = c @ w
        return np.maximum(z, 0, out=z) if shape.act else z

    def behind(layer: int, s: slice, z: np.ndarray, w: np.ndarray, rec: np.ndarray, far: np.ndarray | None) -> None:
        """A strip's share of the gradients goes on the board, the gradients of what went in into d_in."""
        g = outs[layer, s] - x0[s]
        g *= seen[s]
        g *= 2.0 * lams[layer] * share
        if far is not None:
            far = far[s] + d_in[s, d:] if sage else far[s]
            g += np.where(bound[s], 0.0, far) if shape.bound else far
        d_z = g @ rec.T
        if shape.act:
            d_z *= z > 0
        if layer:
            np.matmul(d_z, w[:-1].T, out=d_in[s])
        board[layer, s.start // team.rows] = np.concatenate([(ends[layer, s].T @ d_z).ravel(), (z.T @ g).ravel(), g.sum(axis=0)])

    def passed(theta: dict[str, np.ndarray]):
        h = x0
        for layer in range(shape.layers):
            at = 0 if shape.tie else layer
            w, rec, bias = stacked(theta, at), theta[f"rec{at}.out"], theta[f"rec{at}.bias"]
            near = op[0](h) if layer else first

            def ahead(s: slice, layer=layer, w=w, rec=rec, bias=bias, near=near, h=h) -> None:
                c, out = ends[layer, s], outs[layer, s]
                c[:, :d], c[:, -1] = near[s], 1.0
                if sage:
                    c[:, d:-1] = h[s]
                z = hidden(c, w)
                np.matmul(z, rec, out=out)
                out += bias
                rows[layer, s] = np.where(bound[s], x0[s], out) if shape.bound else out
                if layer == final:
                    behind(layer, s, z, w, rec, None)

            team.each(ahead, strips)
            h = rows[layer]

        def back() -> dict[str, np.ndarray]:
            grads = {}
            for layer in reversed(range(shape.layers)):
                at = 0 if shape.tie else layer
                if layer < final:
                    far, w, rec = op[1](d_in[:, :d]), stacked(theta, at), theta[f"rec{at}.out"]
                    team.each(lambda s, k=layer, w=w, rec=rec, far=far: behind(k, s, hidden(ends[k, s], w), w, rec, far), strips)
                d_w, d_rec, d_bias = np.split(board[layer].sum(axis=0), [wide * f, wide * f + f * d])
                d_w = d_w.reshape(wide, f)
                made = {f"msg{at}.near": d_w[:d], f"msg{at}.bias": d_w[-1:], f"rec{at}.out": d_rec.reshape(f, d), f"rec{at}.bias": d_bias[None]}
                if sage:
                    made[f"msg{at}.self"] = d_w[d:-1]
                for k, v in made.items():
                    grads[k] = grads[k] + v if k in grads else v
            return grads

        return outs[final], h, back

    return passed


def fit(x0: np.ndarray, seen: np.ndarray, truth: np.ndarray, held: np.ndarray, graph: Graph, shape: Shape, train: Training, theta: dict[str, np.ndarray], cores: int = 1) -> tuple[np.ndarray, dict[str, np.ndarray], list[float]]:
    """(rows of the best epoch, the weights that made them, validation errors by epoch).

    The error is taken before the step, so the weights returned make exactly the rows returned; a tie goes to the
    later epoch. Nothing held back: the last epoch is taken. No epochs: the filled input. On several cores the result is
    the same to the bit.
    """
    optimiser = Adam(train.lr, train.decay, train.decoupled)
    best, best_x, best_theta, trace, stale = np.inf, x0, theta, [], 0
    lams = (*train.lams, *[train.lams[-1]] * shape.layers)[: shape.layers]
    by = float(x0.size if train.norm == "all" else seen.sum())
    places = np.nonzero(held)
    real = truth[places]
    make = _taped if shape.module == "gat" else _by_hand
    with Team(1 if make is _taped else max(1, min(cores, len(x0) // SHARE)), STRIP) as team:
        passed = make(x0, seen, shape, graph, team, lams, by)
        team.start()
        for _ in range(train.epochs):
            last, h, back = passed(theta)
            error = float(np.abs(last[places] - real).mean()) if len(real) else -float(len(trace))
            trace.append(error)
            stale += 1
            if error <= best:
                best, best_x, best_theta, stale = error, best_x if team.member else h.copy(), theta, 0
            if train.patience is not None and stale > train.patience:
                break
            theta = optimiser.update(theta, {k: g for k, g in back().items() if not (train.frozen and k.startswith("msg"))})
    return best_x, best_theta, trace


__all__ = ["Adam", "Shape", "Training", "attend", "concat", "fit", "forward", "hold_out", "init", "message", "nbytes"]
