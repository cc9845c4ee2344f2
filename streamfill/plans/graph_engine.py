"""Training one window that is too large for a task: rows and edges stay tables, weights go to all tasks.

Rows are dealt into blocks once, each with its edges, and the blocks are kept by Spark. The loss's gradient is a sum
over rows, so every block adds up its rows' part, and the driver gets sums for each weight. Only the neighbours' mean and
its transpose cross rows: an epoch is one job with two shuffles, in which a block sends to each other block the rows that
it asks for, and gets back their gradients; the first layer's mean does not depend on the weights and is made once.
Nothing goes from epoch to epoch but the weights, so a lost executor repeats its tasks only. Two-layer networks of the
self-plus-mean module.
"""

from __future__ import annotations

import gc
import pickle
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from streamfill.functions import nets
from streamfill.functions.autodiff import Adam
from streamfill.operators import fill, graph, masks
from streamfill.plans.impute import Options, seeded
from streamfill.schema import attributes
from streamfill.sources.durable import settle

#: Rows of a block at least, and at most where blocks are as many as tasks side by side already.
ROWS, MOST = 2048, 65536


def _spread(vectors: DataFrame, edges: DataFrame, dims: int, column: str, transposed: bool = False) -> DataFrame:
    """(inst_id, column): weighted sums of neighbours' vectors, or of the transpose."""
    near, far = ("dst", "src") if transposed else ("src", "dst")
    joined = edges.join(vectors.select(F.col("inst_id").alias(far), F.col(column).alias("v")), far)
    return joined.groupBy(F.col(near).alias("inst_id")).agg(F.array(*(F.sum(F.col("w") * F.get("v", F.lit(d))) for d in range(dims))).alias(column))


def _cells(column: pa.ChunkedArray, d: int) -> np.ndarray:
    return column.combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(-1, d)


def _blocks(nodes: DataFrame, edges: DataFrame, d: int, many: int):
    """An RDD of `many` partitions with one block each (None where no row fell): its rows' matrices, which of its rows other
    blocks ask for, and its edges by place among what it gets, that is the rows it asks for by block and id."""
    block = lambda c: F.pmod(F.xxhash64(c), F.lit(many)).cast("int")
    ends = edges.select("src", "dst", "w", block("src").alias("near"), block("dst").alias("far"))
    both = ends.select(F.col("near").alias("b"), F.lit(True).alias("own"), "*").unionByName(ends.select(F.col("far").alias("b"), F.lit(False).alias("own"), "*"))

    def made(key: tuple, left: pa.Table, right: pa.Table) -> pa.Table:
        left = left.sort_by("inst_id")
        ids = left["inst_id"].to_numpy()
        own = right["own"].to_numpy()
        src, dst, w, near, far = (right[c].to_numpy() for c in ("src", "dst", "w", "near", "far"))
        asked = {int(k): np.searchsorted(ids, np.unique(dst[~own & (near == k)])) for k in np.unique(near[~own])}
        order = np.lexsort((dst, far, src))
        order = order[own[order]]
        src, dst, w, far = (v[order] for v in (src, dst, w, far))
        gets, place, at = [], np.zeros(len(dst), np.int64), 0
        for k in np.unique(far):
            some = far == k
            kinds, place[some] = np.unique(dst[some], return_inverse=True)
            place[some] += at
            gets.append((int(k), len(kinds)))
            at += len(kinds)
        held = {"me": int(key[0]), "ids": ids, "asked": asked, "gets": gets, "src": np.searchsorted(ids, src), "place": place, "w": w}
        held |= {c: _cells(left[c], d) for c in ("x0", "seen", "near0", "real", "truth")}
        return pa.table({"b": pa.array([key[0]], pa.int32()), "block": pa.array([pickle.dumps(held)], pa.binary())})

    rows = nodes.withColumn("b", block("inst_id"))
    packed = settle(rows.groupBy("b").cogroup(both.groupBy("b")).applyInArrow(made, "b int, block binary"))
    dealt = packed.rdd.map(lambda r: (r.b, bytes(r.block))).partitionBy(many, int)
    return dealt.mapPartitions(lambda it: [next((pickle.loads(v) for _, v in it), None)])


def _summed(at: np.ndarray, w: np.ndarray, rows: np.ndarray, n: int) -> np.ndarray:
    return np.column_stack([np.bincount(at, w * rows[:, k], n) for k in range(rows.shape[1])])


def _met(blocks, messages, many: int):
    """Each block with what was sent to it."""
    return blocks.zip(messages.partitionBy(many, int).mapPartitions(lambda it: [[m for _, m in it]]))


def _forward(w: dict, layer: int, h: np.ndarray, near: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    pre = h @ w[f"msg{layer}.self"] + near @ w[f"msg{layer}.near"] + w[f"msg{layer}.bias"]
    z = np.maximum(pre, 0)
    return pre, z, z @ w[f"rec{layer}.out"] + w[f"rec{layer}.bias"]


def _backward(w: dict, layer: int, h: np.ndarray, near: np.ndarray, pre: np.ndarray, z: np.ndarray, d_out: np.ndarray) -> tuple[dict, np.ndarray]:
    d_pre = (d_out @ w[f"rec{layer}.out"].T) * (pre > 0)
    grads = {f"msg{layer}.self": h.T @ d_pre, f"msg{layer}.near": near.T @ d_pre, f"msg{layer}.bias": d_pre.sum(axis=0, keepdims=True), f"rec{layer}.out": z.T @ d_out, f"rec{layer}.bias": d_out.sum(axis=0, keepdims=True)}
    return grads, d_pre


def _flat(grads: dict, names: list[str], shapes: dict) -> np.ndarray:
    return np.concatenate([grads.get(k, np.zeros(shapes[k])).ravel() for k in names])


def fit_impute(chunk: DataFrame, o: Options, theta: dict | None = None) -> tuple[DataFrame, dict, list[float]]:
    """(imputed chunk of one window, best weights, validation errors). Held-out cells are drawn by the portable hash."""
    xs = attributes(chunk)
    d, n = len(xs), chunk.count()
    held = masks.remove_cells(chunk, o.beta, o.seed)[0]
    base = fill.mean_fill(held)
    edges = settle(graph.normalise(graph.knn(base, o.k, o.metric, o.graph), "row").select("src", "dst", "w"))
    vec = lambda prefix, f: F.array(*(f(c) for c in xs)).alias(prefix)
    flag = lambda c: F.col(c).isNotNull().cast("double")
    nodes = base.select("inst_id", vec("x0", F.col)).join(held.select("inst_id", vec("seen", flag)), "inst_id")
    nodes = nodes.join(chunk.select("inst_id", vec("real", flag), vec("truth", lambda c: F.coalesce(c, F.lit(0.0)))), "inst_id")
    zero = F.array(*(F.lit(0.0) for _ in xs))
    with_default = lambda left, right, c: left.join(right, "inst_id", "left").withColumn(c, F.coalesce(c, zero))
    nodes = settle(with_default(nodes, _spread(nodes.select("inst_id", F.col("x0").alias("near0")), edges, d, "near0"), "near0"))

    shape = o.shape(d)
    if shape.module != "sage" or shape.layers != 2:
        raise ValueError("the graph engine trains two layers of the sage module")
    theta = nets.init(shape, seeded(o.seed)) | (theta or {})
    names, shapes = list(theta), {k: v.shape for k, v in theta.items()}
    optimiser, lams = Adam(o.lr, o.decay, o.decoupled), o.lams
    cells = float(n * d) if o.norm == "all" else float(nodes.select(F.sum(F.aggregate("seen", F.lit(0.0), lambda a, b: a + b))).first()[0])
    best, best_theta, trace = np.inf, theta, []
    side_by_side = 2 * chunk.sparkSession.sparkContext.defaultParallelism
    many = max(1, min(-(-n // ROWS), max(side_by_side, -(-n // MOST))))
    blocks = _blocks(nodes, edges, d, many).persist(StorageLevel.MEMORY_AND_DISK)

    def first(w: dict) -> Callable:
        def step(b: dict | None) -> Iterator[tuple]:
            if b:
                h = np.where(b["seen"] > 0, b["x0"], _forward(w, 0, b["x0"], b["near0"])[2])
                yield b["me"], (-1, h)
                yield from ((k, (b["me"], h[rows])) for k, rows in b["asked"].items())

        return step

    def second(w: dict, only_rows: bool = False) -> Callable:
        def step(pair: tuple) -> Iterator[tuple]:
            b, came = pair[0], dict(pair[1])
            if not b:
                return
            x0, seen, h = b["x0"], b["seen"], came[-1]
            got = np.concatenate([np.zeros((0, d)), *(came[k] for k, _ in b["gets"])])
            near = _summed(b["src"], b["w"], got[b["place"]], len(h))
            pre, z, out = _forward(w, 1, h, near)
            if only_rows:
                yield from zip(b["ids"].tolist(), np.where(seen > 0, x0, out).tolist(), strict=True)
                return
            grads, d_pre = _backward(w, 1, h, near, pre, z, 2 * lams[1] / cells * (out - x0) * seen)
            check = (b["real"] > 0) & (seen == 0)
            tail = [np.abs(out - b["truth"])[check].sum(), float(check.sum())]
            yield b["me"], (-1, (d_pre @ w["msg1.self"].T, np.concatenate([_flat(grads, names, shapes), tail])))
            back, at = _summed(b["place"], b["w"], (d_pre @ w["msg1.near"].T)[b["src"]], len(got)), 0
            for k, size in b["gets"]:
                yield k, (b["me"], back[at : at + size])
                at += size

        return step

    def third(w: dict) -> Callable:
        def step(pair: tuple) -> Iterator[np.ndarray]:
            b, came = pair[0], dict(pair[1])
            if not b:
                return
            x0, seen, near = b["x0"], b["seen"], b["near0"]
            d_h, part = came.pop(-1)
            for k in sorted(came):
                d_h[b["asked"][k]] += came[k]
            pre, z, out = _forward(w, 0, x0, near)
            grads, _ = _backward(w, 0, x0, near, pre, z, d_h * (1 - seen) + 2 * lams[0] / cells * (out - x0) * seen)
            part[:-2] += _flat(grads, names, shapes)
            yield part

        return step

    def passed(w: dict, only_rows: bool = False):
        return _met(blocks, blocks.flatMap(first(w)), many).flatMap(second(w, only_rows))

    for _ in range(o.epochs):
        parts = _met(blocks, passed(theta), many).flatMap(third(theta))
        added = parts.treeReduce(np.add) if many > 64 else sum(parts.collect())
        error = added[-2] / added[-1] if added[-1] else -float(len(trace))
        trace.append(error)
        if error <= best:
            best, best_theta = error, theta
        grads, at = {}, 0
        for k in names:
            grads[k] = added[at : at + theta[k].size].reshape(shapes[k])
            at += theta[k].size
        theta = optimiser.update(theta, grads)
        if len(trace) % 10 == 0:  # what epochs have shuffled stays on disk until both collectors have been through
            del parts
            gc.collect()
            chunk.sparkSession.sparkContext._jvm.System.gc()
    rows = settle(chunk.sparkSession.createDataFrame(passed(best_theta, True), "inst_id long, out array<double>"))
    blocks.unpersist()
    made = chunk.join(rows, "inst_id").select("window_id", "stream_id", "inst_id", *(F.coalesce(c, F.get("out", F.lit(k))).alias(c) for k, c in enumerate(xs)))
    return made, best_theta, trace
