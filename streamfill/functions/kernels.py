"""Graphs and classical imputers on one window's matrix. Missing cells are NaN, rows are sorted by id."""

from __future__ import annotations

import mmap
import os
import warnings
from functools import cached_property

import numpy as np

#: Numbers a block of distances holds at most.
BLOCK = 4_000_000
#: Windows up to this size multiply by a dense matrix.
DENSE = 500


def mean_filled(x: np.ndarray) -> np.ndarray:
    """Column means over observed cells; 0 where a column has none."""
    seen = ~np.isnan(x)
    n = seen.sum(axis=0)
    mean = np.where(n > 0, np.where(seen, x, 0.0).sum(axis=0) / np.maximum(n, 1), 0.0)
    return np.where(seen, x, mean)


def distances(a: np.ndarray, b: np.ndarray, metric: str = "euclidean") -> np.ndarray:
    if metric == "cosine":
        na, nb = np.linalg.norm(a, axis=1), np.linalg.norm(b, axis=1)
        scale = na[:, None] * nb[None, :]
        return np.where(scale > 0, 1 - a @ b.T / np.where(scale > 0, scale, 1), 1.0)
    if a.shape[0] * b.shape[0] * a.shape[1] <= BLOCK * 4:
        return ((a[:, None, :] - b[None, :, :]) ** 2).sum(axis=2)
    return np.maximum((a * a).sum(axis=1)[:, None] + (b * b).sum(axis=1)[None, :] - 2 * a @ b.T, 0)


def nearest(x: np.ndarray, k: int, metric: str = "euclidean") -> np.ndarray:
    """Places of each row's k nearest other rows, nearest first, ties by place.

    Rows of equal values are one class and are compared once. Of the k + 1 rows nearest to a class by distance and place
    (itself included), each belongs to one of the k + 1 classes nearest by distance and least place, and is among the
    k + 1 least places there; each row takes that list without itself. Exact, and n * n is never held.
    """
    n = len(x)
    k = min(k, n - 1)
    if k < 1:
        return np.zeros((n, 0), np.int64)
    order = np.lexsort(x.T[::-1])
    starts = np.flatnonzero(np.concatenate([[True], (x[order][1:] != x[order][:-1]).any(axis=1)]))
    size = np.diff([*starts, n])
    own = np.empty(n, np.int64)
    own[order] = np.repeat(np.arange(len(starts)), size)
    least = order[starts]
    by_place = np.argsort(least)  # so that ties by number are ties by place
    number = np.argsort(by_place)
    own, starts, size, kinds = number[own], starts[by_place], size[by_place], x[least[by_place]]
    top = min(k + 1, len(kinds))
    search = _by_leaves if metric == "euclidean" and len(kinds) > 4 * LEAF else _by_blocks
    gap, near = search(kinds, top, metric)
    out = np.empty((n, k), np.int64)
    lists = np.empty((len(kinds), k + 1), np.int64)
    for at in range(0, len(kinds), 8192):
        some = near[at : at + 8192].ravel()
        held = np.minimum(size[some], k + 1)
        ends = np.cumsum(held)
        place = order[np.repeat(starts[some] - ends + held, held) + np.arange(ends[-1])]
        asks = np.repeat(np.arange(len(some)) // top, held)
        rank = np.lexsort((place, np.repeat(gap[at : at + 8192].ravel(), held), asks))
        first = np.searchsorted(asks, np.arange(len(some) // top))
        lists[at : at + 8192] = place[rank][first[:, None] + np.arange(k + 1)]
    for at in range(0, n, 65536):
        found = lists[own[at : at + 65536]]
        mine = found == np.arange(at, at + len(found))[:, None]
        kept = np.ones(found.shape, bool)
        kept[np.arange(len(found)), np.where(mine.any(axis=1), mine.argmax(axis=1), k)] = False
        out[at : at + 65536] = found[kept].reshape(-1, k)
    return out


#: Rows of a leaf of the search tree, about, and of a strip of distances.
LEAF, STRIP = 64, 64


def _gaps(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Squared distances, summed attribute by attribute in place."""
    out = None
    for d in range(a.shape[1]):
        term = np.subtract.outer(a[:, d], b[:, d])
        term *= term
        out = term if out is None else np.add(out, term, out=out)
    return out


def _least(d: np.ndarray, number: np.ndarray, top: int) -> tuple[np.ndarray, np.ndarray]:
    """(values, numbers) of each row's `top` least, in order of value and number; number has one row or as many as d."""
    if d.shape[1] > top:
        limit = np.partition(d, top - 1, axis=1)[:, top - 1]
        i, j = np.nonzero(d <= limit[:, None])
    else:
        i, j = (v.ravel() for v in np.indices(d.shape))
    v, c = d[i, j], (number[j] if number.ndim == 1 else number[i, j])
    rank = np.lexsort((c, v, i))
    at = rank[np.searchsorted(i, np.arange(len(d)))[:, None] + np.arange(top)]  # i is sorted, and each row has `top` or more
    return v[at], c[at]


def _by_blocks(x: np.ndarray, top: int, metric: str) -> tuple[np.ndarray, np.ndarray]:
    """(distances, places) of each row's `top` nearest rows, itself included, in order of distance and place."""
    value, found = np.empty((len(x), top)), np.empty((len(x), top), np.int64)
    step = STRIP if len(x) > STRIP * STRIP else max(STRIP, BLOCK // 16 // len(x))
    for at in range(0, len(x), step):
        some = slice(at, at + step)
        value[some], found[some] = _least(_gaps(x[some], x) if metric == "euclidean" else distances(x[some], x, metric), np.arange(len(x)), top)
    return value, found


def _leaves(x: np.ndarray) -> list[np.ndarray]:
    """Places dealt into leaves by halves along the widest attribute; a value that over half of the rows have is a part of
    its own (filled cells are alike)."""
    out, todo = [], [np.arange(len(x))]
    while todo:
        some = todo.pop()
        if len(some) <= LEAF:
            out.append(some)
            continue
        held = x[some]
        d, mid = int(np.argmax(held.max(axis=0) - held.min(axis=0))), len(some) // 2
        cut = np.argpartition(held[:, d], mid)
        at = held[:, d] - held[cut[mid], d]
        if len(some) < 2 * np.count_nonzero(at == 0) < 2 * len(some):
            todo += [part for part in (some[at < 0], some[at > 0], some[at == 0]) if len(part)]
        else:
            todo += [some[cut[mid:]], some[cut[:mid]]]
    return out


def _by_leaves(x: np.ndarray, top: int, metric: str = "euclidean") -> tuple[np.ndarray, np.ndarray]:
    """As _by_blocks. A leaf's rows meet the nearest leaves first, then those whose box is no further from some row than
    its last neighbour so far. Distances to boxes are summed in the order of those to rows, so rounding loses none."""
    value, found = np.empty((len(x), top)), np.empty((len(x), top), np.int64)
    leaves = _leaves(x)
    low, high = (np.stack([f(x[a], axis=0) for a in leaves]) for f in (np.min, np.max))

    def to_boxes(a: np.ndarray, z: np.ndarray, some: np.ndarray) -> np.ndarray:
        """From boxes a..z to leaves."""
        out = None
        for d in range(x.shape[1]):
            gap = np.maximum(np.maximum(np.subtract.outer(low[some, d], z[:, d]), np.subtract.outer(high[some, d], a[:, d]) * -1), 0)
            gap *= gap
            out = gap if out is None else np.add(out, gap, out=out)
        return out.T

    every = np.arange(len(leaves))
    first = -(-2 * top // LEAF) + 2
    for k, rows in enumerate(leaves):
        own = x[rows]
        away = to_boxes(low[k : k + 1], high[k : k + 1], every)[0]
        order, at, v, c = np.argsort(away, kind="stable"), 0, None, None
        while at < len(order):
            some = order[at : at + (4 * first if v is not None else first)]
            at += len(some)
            if v is not None:
                last = v[:, -1] if v.shape[1] == top else np.full(len(own), np.inf)
                if away[some[0]] > last.max():
                    break
                some = some[(to_boxes(own, own, some) <= last[:, None]).any(axis=0)]
                if not len(some):
                    continue
            number = np.concatenate([leaves[b] for b in some])
            new = _least(_gaps(own, x[number]), number, min(top, len(number)))
            if v is None:
                v, c = new
            else:
                v, c = _least(np.concatenate([v, new[0]], axis=1), np.concatenate([c, new[1]], axis=1), min(top, v.shape[1] + new[0].shape[1]))
        value[rows], found[rows] = v, c
    return value, found


#: Nodes that a slot of neighbours has at least.
SLOT = 64


class Team:
    """One task's strips on several cores. After start() every member, a process each, goes through the same steps and does
    its share of each(); arrays made by array() before are everyone's, all else is a member's own. A strip's result does not
    depend on who makes it, so the results are those of one member to the bit. Threads would wait for the interpreter.

    Leaving the block ends the others; one that fails, or whose first member is gone, ends as well."""

    def __init__(self, size: int = 1, rows: int = 1024) -> None:
        self.size, self.rows, self.member, self.links, self.others = size, rows, 0, [], []

    def array(self, shape: tuple[int, ...]) -> np.ndarray:
        if self.size == 1 or not np.prod(shape):
            return np.zeros(shape)
        return np.frombuffer(mmap.mmap(-1, int(np.prod(shape)) * 8), np.float64).reshape(shape)

    def strips(self, n: int) -> list[slice]:
        return [slice(a, min(a + self.rows, n)) for a in range(0, n, self.rows)]

    def start(self) -> None:
        for member in range(1, self.size):
            (ours_in, theirs_out), (theirs_in, ours_out) = os.pipe(), os.pipe()
            with warnings.catch_warnings():
                warnings.simplefilter("ignore", DeprecationWarning)  # threads of Arrow, which the others do not use
                pid = os.fork()
            if not pid:
                for at in (ours_in, ours_out, *(at for link in self.links for at in link)):
                    os.close(at)
                self.member, self.links, self.others = member, [(theirs_in, theirs_out)], []
                return
            os.close(theirs_in)
            os.close(theirs_out)
            self.links.append((ours_in, ours_out))
            self.others.append(pid)

    def each(self, f, strips) -> None:
        """f of every strip; after it, all is done."""
        for strip in strips[self.member :: self.size] if self.links else strips:
            f(strip)
        if self.member:
            at, to = self.links[0]
            os.write(to, b".")
            if not os.read(at, 1):
                os._exit(1)
        elif self.links:
            if not all([os.read(at, 1) for at, _ in self.links]):
                raise RuntimeError("a process that shared a window's work has ended")
            for _, to in self.links:
                os.write(to, b".")

    def __enter__(self):
        return self

    def __exit__(self, kind, error, trace) -> None:
        if self.member:
            os._exit(0 if kind is None else 1)
        for link in self.links:
            for at in link:
                os.close(at)
        for pid in self.others:
            os.waitpid(pid, 0)
        self.links, self.others = [], []


class Graph:
    """An undirected graph as directed edges sorted by (src, dst)."""

    def __init__(self, n: int, src: np.ndarray, dst: np.ndarray) -> None:
        code = np.sort(np.concatenate([src * n + dst, dst * n + src])) if n else np.zeros(0, np.int64)
        code = code[np.concatenate([[True], code[1:] != code[:-1]])] if len(code) else code
        self.n, self.src, self.dst = n, code // max(n, 1), code % max(n, 1)
        keep = self.src != self.dst
        self.src, self.dst = self.src[keep], self.dst[keep]
        self.degree = np.bincount(self.src, minlength=n)
        self.nodes, self.starts = np.unique(self.src, return_index=True)
        self.owner = np.repeat(np.arange(len(self.nodes)), self.degree[self.nodes])

    @cached_property
    def back(self) -> np.ndarray:
        """Where the edge in the other direction stands."""
        return np.lexsort((self.src, self.dst))

    def weights(self, how: str) -> np.ndarray:
        if how == "sym":
            return 1 / np.sqrt(self.degree[self.src] * self.degree[self.dst])
        return 1 / self.degree[self.src] if how == "row" else np.ones(len(self.src))

    def operator(self, how: str, team: Team | None = None, dims: int = 0):
        """(H -> S H, G -> S' G) for the weighted adjacency S: by rows the mean of neighbours, or (sym) weights of one by the
        root of both degrees. Links go both ways, so S' differs in its weights only, which are factors of the ends. With a
        team, for so many columns: each call is the whole team's and fills the array that the call before gave."""
        if self.n <= DENSE:
            s = np.zeros((self.n, self.n))
            s[self.src, self.dst] = self.weights(how)
            return (lambda h: s @ h), (lambda g: s.T @ g)
        team = team or Team()
        room, out = (team.array((self.n, dims)) if dims else None for _ in range(2))
        if how not in ("row", "sym"):
            return (lambda h: self.summed(h, team, out)), (lambda g: self.summed(g, team, out))
        by = 1 / np.maximum(self.degree, 1)[:, None]
        if how == "sym":
            by = np.sqrt(by)

        def scaled(h: np.ndarray, to: np.ndarray | None) -> np.ndarray:
            to = np.empty(h.shape) if to is None else to
            team.each(lambda s: np.multiply(by[s], h[s], out=to[s]), team.strips(self.n))
            return to

        def ahead(h: np.ndarray) -> np.ndarray:
            made = self.summed(scaled(h, room) if how == "sym" else h, team, out)
            return scaled(made, made)

        def back(g: np.ndarray) -> np.ndarray:
            made = self.summed(scaled(g, room), team, out)
            return scaled(made, made) if how == "sym" else made

        self.slots  # noqa: B018 (made once, before a team parts)
        return ahead, back

    def gather(self, w: np.ndarray, h: np.ndarray) -> np.ndarray:
        """Sums under any weights of edges."""
        out = np.zeros((self.n, h.shape[1]))
        if len(self.src):
            out[self.nodes] = np.add.reduceat(w[:, None] * h[self.dst], self.starts, axis=0)
        return out

    @cached_property
    def slots(self) -> tuple[np.ndarray, list[np.ndarray], tuple]:
        """(nodes in order of their degree, their first neighbours side by side, then their second, and so on; what few
        nodes have more)."""
        begin = np.cumsum(self.degree) - self.degree
        order = np.argsort(-self.degree, kind="stable")
        falls, slots = self.degree[order], []
        while (c := int(np.searchsorted(-falls, -len(slots), "left"))) >= SLOT:
            slots.append(self.dst[begin[order[:c]] + len(slots)])
        more, left = order[:c], falls[:c] - len(slots)
        ends = np.cumsum(left)
        return order, slots, (c, ends - left, self.dst[np.repeat(begin[more] + len(slots) - ends + left, left) + np.arange(left.sum())])

    def summed(self, h: np.ndarray, team: Team | None = None, out: np.ndarray | None = None) -> np.ndarray:
        """Sums of h over neighbours, slot by slot for a strip of nodes; what few nodes have more, edge by edge."""
        order, slots, (c, starts, rest) = self.slots
        out, team = np.empty((self.n, h.shape[1])) if out is None else out, team or Team()

        def few(d: int) -> None:
            out[order[:c], d] += np.add.reduceat(h[:, d].take(rest), starts)

        def strip(s: slice) -> None:
            made = np.zeros((s.stop - s.start, h.shape[1]))
            for far in slots:
                if len(far) <= s.start:
                    break
                held = h.take(far[s], axis=0, mode="clip")
                made[: len(held)] += held
            out[order[s]] = made

        team.each(strip, team.strips(self.n))
        if c:
            team.each(few, range(h.shape[1]))
        return out


def build_graph(filled: np.ndarray, k: int = 10, metric: str = "euclidean", mode: str = "union", eps: float | None = None) -> Graph:
    """Neighbour graph (union or mutual) or, with eps, threshold graph (share of the mean distance for that is scale-free)."""
    n = len(filled)
    if eps is not None:
        step = max(1, BLOCK // max(1, n * max(1, filled.shape[1])))
        src, dst = [], []
        for at in range(0, n, step):
            d = distances(filled[at : at + step], filled, metric)
            i, j = np.nonzero(d < (eps * eps if metric == "euclidean" else eps))
            src.append(i + at)
            dst.append(j)
        return Graph(n, np.concatenate(src or [np.zeros(0, int)]), np.concatenate(dst or [np.zeros(0, int)]))
    near = nearest(filled, k, metric)
    src, dst = np.repeat(np.arange(n), near.shape[1]), near.ravel()
    if mode == "mutual":
        both = np.isin(src * n + dst, dst * n + src)
        src, dst = src[both], dst[both]
    return Graph(n, src, dst)


def feature_propagation(x: np.ndarray, graph: Graph, iters: int = 40, tol: float | None = None, how: str = "sym", bounded: bool = True) -> np.ndarray:
    forward, _ = graph.operator(how)
    seen, now = ~np.isnan(x), mean_filled(x)
    alone = graph.degree == 0
    for _ in range(iters):
        new = forward(now)
        new[alone] = now[alone]
        if bounded:
            new = np.where(seen, x, new)
        moved = np.abs(new - now).max(initial=0.0)
        now = new
        if tol is not None and moved < tol:
            break
    return now


def knn_impute(x: np.ndarray, k: int = 10, metric: str = "filled") -> np.ndarray:
    """Mean of the nearest rows that observe the attribute; metric nan compares common cells only."""
    seen, base = ~np.isnan(x), mean_filled(x)
    out, n = base.copy(), len(x)
    if n < 2:
        return out
    zero = np.where(seen, x, 0.0)
    step = max(1, BLOCK // max(1, n * x.shape[1]))
    for at in range(0, n, step):
        if metric == "nan":
            a, m = zero[at : at + step], seen[at : at + step].astype(float)
            both = m @ seen.T.astype(float)
            d = (a * a) @ seen.T.astype(float) + m @ (zero * zero).T - 2 * a @ zero.T
            d = np.where(both > 0, d / np.maximum(both, 1), np.inf)
        else:
            d = distances(base[at : at + step], base)
        d[np.arange(len(d)), np.arange(at, at + len(d))] = np.inf
        for i, row in enumerate(d):
            for j in np.flatnonzero(~seen[at + i]):
                have = np.flatnonzero(seen[:, j] & np.isfinite(row))
                if len(have):
                    if len(have) > k:
                        have = have[np.argpartition(row[have], k - 1)[:k]]
                    out[at + i, j] = x[have, j].mean()
    return out


def mice(x: np.ndarray, rounds: int = 5, ridge: float = 1e-2, draws: int = 0, seed: int = 0) -> np.ndarray:
    """Round-robin ridge regressions; with draws, the mean of chains whose predictions carry residual noise."""
    if draws:
        return np.mean([_chain(x, rounds, ridge, np.random.default_rng([seed, d])) for d in range(draws)], axis=0)
    return _chain(x, rounds, ridge, None)


def _chain(x: np.ndarray, rounds: int, ridge: float, rng: np.random.Generator | None) -> np.ndarray:
    seen, now = ~np.isnan(x), mean_filled(x)
    for _ in range(rounds):
        for j in range(x.shape[1]):
            rows, holes = seen[:, j], ~seen[:, j]
            if not holes.any() or rows.sum() < 2:
                continue
            others = np.delete(now, j, axis=1)
            a = np.column_stack([np.ones(len(x)), others])
            gram = a[rows].T @ a[rows] + ridge * rows.sum() * np.diag([0.0, *np.ones(others.shape[1])])
            beta = np.linalg.lstsq(gram, a[rows].T @ x[rows, j], rcond=None)[0]
            now[holes, j] = a[holes] @ beta
            if rng is not None:
                now[holes, j] += rng.normal(0, np.std(x[rows, j] - a[rows] @ beta), holes.sum())
    return now


def mf(x: np.ndarray, rank: int | None = None, iters: int = 100, shrink: float | None = None, tol: float = 1e-5) -> np.ndarray:
    """Repeated truncated (or, with shrink, soft-thresholded) singular value decomposition, through the D x D Gramian."""
    seen, now = ~np.isnan(x), mean_filled(x)
    rank = min(rank or min(8, x.shape[1]), x.shape[1])
    for _ in range(iters):
        values, vectors = np.linalg.eigh(now.T @ now)
        if shrink is None:
            v = vectors[:, -rank:]
            new = now @ v @ v.T
        else:
            s = np.sqrt(np.maximum(values, 0))
            new = now @ (vectors * (np.maximum(s - shrink, 0) / np.where(s > 0, s, 1))) @ vectors.T
        new = np.where(seen, x, new)
        moved = np.abs(new - now).max(initial=0.0)
        now = new
        if moved < tol:
            break
    return now


def importance(seen: np.ndarray) -> np.ndarray:
    """Normalised importance of rows, by column counts."""
    n, d = seen.shape
    own = seen.sum(axis=1)
    if n <= 1:
        return np.minimum(own, max(1, d - 1)) / max(1, d - 1)
    return (n * own - seen @ seen.sum(axis=0)) / (n - 1) / max(1, d - 1)


def importance_gram(seen: np.ndarray) -> np.ndarray:
    """The same through the product of the mask with itself (the reference; quadratic in the rows)."""
    m = seen.astype(float)
    g = m @ m.T
    n, d = m.shape
    return (n * np.diag(g) - g.sum(axis=1)) / max(1, n - 1) / max(1, d - 1)
