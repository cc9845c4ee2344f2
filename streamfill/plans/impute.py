"""Snapshot imputation: every window by itself, by any method, many windows at once.

Chunks are scaled first if asked, dealt by window once, and each is imputed where it lands: graph, training and all.
A window is one problem whatever its size; only a caller who gives max_rows has larger windows split.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field, fields

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from streamfill.functions import kernels, nets, sequence
from streamfill.operators import windows
from streamfill.operators.fill import Scaler
from streamfill.plans.groups import by_group
from streamfill.schema import attributes

METHODS = ("mean", "zero", "knn", "mice", "mf", "fp", "brits", "saits", "propnet")


@dataclass(frozen=True)
class Options:
    """One method and its settings; what a method does not know it ignores."""

    method: str = "propnet"
    k: int = 10
    metric: str = "euclidean"
    graph: str = "union"
    eps: float | None = None
    module: str = "sage"
    width: int | None = None
    layers: int = 2
    bound: bool = True
    act: bool = True
    epochs: int = 200
    beta: float = 0.05
    lr: float = 0.01
    decay: float = 0.1
    decoupled: bool = False
    lams: tuple = (1.0, 1.0)
    norm: str = "all"
    patience: int | None = None
    iters: int = 40
    tol: float | None = None
    rank: int | None = None
    shrink: float | None = None
    rounds: int = 5
    draws: int = 0
    knn_metric: str = "filled"
    hidden: int = 32
    heads: int = 2
    seq_epochs: int = 30
    init: str = "mean"
    seed: int = 0
    # between windows
    mode: str = "periodic"
    update: str = "message"
    eta: float = 0.6
    eta_mode: str = "absolute"
    max_cache: int | None = None
    label: str = field(default="", compare=False)

    def shape(self, dims: int) -> nets.Shape:
        return nets.Shape(dims, self.width, self.layers, self.module, self.bound, self.act)

    def training(self) -> nets.Training:
        return nets.Training(self.epochs, self.beta, self.lr, self.decay, self.decoupled, self.lams, self.norm, self.patience, self.update == "frozen")


@dataclass
class Outcome:
    x: np.ndarray
    theta: dict | None = None
    trace: list | None = None
    graph_s: float = 0.0
    total_s: float = 0.0
    model_bytes: int = 0

    @property
    def best_epoch(self) -> int:
        """The epoch chosen (the last of the least errors); -1 without training."""
        return len(self.trace) - 1 - int(np.argmin(self.trace[::-1])) if self.trace else -1


def seeded(seed: int, *key: int | None) -> np.random.Generator:
    return np.random.default_rng([seed, *(int(k or 0) & 0xFFFFFFFF for k in key)])


def impute_window(x: np.ndarray, o: Options, key: tuple = (), streams: np.ndarray | None = None, times: np.ndarray | None = None, theta: dict | None = None, cores: int = 1) -> Outcome:
    """One window's rows (NaN where missing). theta: weights to start from; what it lacks is drawn. cores: those that the
    network's training may use."""
    began = time.perf_counter()
    seen, rng = ~np.isnan(x), seeded(o.seed, *key)
    out = Outcome(x)
    n = len(x)
    if o.method == "propnet":
        held = nets.hold_out(seen, o.beta, rng)
        base = kernels.mean_filled(np.where(held, np.nan, x))
        graph = kernels.build_graph(base, o.k, o.metric, o.graph, o.eps)
        out.graph_s = time.perf_counter() - began
        left = seen & ~held
        x0 = base if o.init == "mean" else np.where(left, x, 0.0)
        shape = o.shape(x.shape[1])
        start = nets.init(shape, rng) | (theta or {})
        out.x, out.theta, out.trace = nets.fit(x0, left.astype(float), np.where(seen, x, 0.0), held, graph, shape, o.training(), start, cores)
        out.model_bytes = nets.nbytes(start)
    elif o.method == "fp":
        base = kernels.mean_filled(x)
        graph = kernels.build_graph(base, o.k, o.metric, o.graph, o.eps)
        out.graph_s = time.perf_counter() - began
        out.x = kernels.feature_propagation(x, graph, o.iters, o.tol, bounded=o.bound)
    elif o.method == "knn":
        out.x = kernels.knn_impute(x, o.k, o.knn_metric)
    elif o.method == "mice":
        out.x = kernels.mice(x, o.rounds, draws=o.draws, seed=o.seed)
    elif o.method == "mf":
        out.x = kernels.mf(x, o.rank, shrink=o.shrink)
    elif o.method in ("brits", "saits"):
        streams = np.zeros(n, int) if streams is None else streams
        times = np.arange(n) if times is None else times
        made = sequence.brits(x, streams, times, o.hidden, o.seq_epochs, seed=o.seed) if o.method == "brits" else sequence.saits(x, streams, times, o.hidden, o.heads, o.seq_epochs, seed=o.seed)
        out.x, out.model_bytes = made
    elif o.method == "zero":
        out.x = np.zeros_like(x)
    elif o.method == "mean":
        out.x = kernels.mean_filled(x)
    else:
        raise ValueError(f"unknown method {o.method}; known: {', '.join(METHODS)}")
    out.x = np.where(seen, x, np.where(np.isfinite(out.x), out.x, 0.0))  # observed cells stay to the bit
    out.total_s = time.perf_counter() - began
    return out


def matrix(rows: pa.Table, xs: list[str]) -> np.ndarray:
    """The attribute columns as one matrix; nulls become NaN."""
    return np.column_stack([rows[c].to_numpy().astype(np.float64) for c in xs])


def stream_codes(rows: pa.Table) -> np.ndarray:
    return rows["stream_id"].combine_chunks().dictionary_encode("encode").indices.to_numpy(zero_copy_only=False) if rows.num_rows else np.zeros(0, int)


STATS = "graph_s double, total_s double, best_epoch int, cached int, model_bytes long"


def times_of(rows: pa.Table) -> np.ndarray:
    return rows["inst_id"].fill_null(0).to_numpy()


def result(rows: pa.Table, xs: list[str], x: np.ndarray, out: Outcome, extra: dict, cached: int = 0, **more) -> pa.Table:
    n = rows.num_rows
    same = lambda v, t: pa.array(np.full(n, v), t)
    columns = {k: v for k, v in extra.items()} | {c: rows[c] for c in ("window_id", "stream_id", "inst_id")}
    columns |= {c: pa.array(x[:, d]) for d, c in enumerate(xs)}
    columns |= more
    columns |= {"graph_s": same(out.graph_s, pa.float64()), "total_s": same(out.total_s, pa.float64()), "best_epoch": same(out.best_epoch, pa.int32()), "cached": same(cached, pa.int32()), "model_bytes": same(out.model_bytes, pa.int64())}
    return pa.table(columns)


def run_windows(df: DataFrame, options: dict[int, Options], scaler: Scaler | None = None) -> DataFrame:
    """(cfg, keys, x..., is_imputed, figures): every window under every setting, in one job. df may hold a column cfg
    already. With a scaler, methods see scaled values, and what comes out is on the scale of df. One row comes out for
    each that goes in, whatever its ids: a null window is a window of its own, and repeated ids are rows like any others.
    """
    xs = attributes(df)
    if "cfg" not in df.columns:
        df = df.withColumn("cfg", F.explode(F.array(*(F.lit(k).cast("int") for k in options))))
    if "sub" not in df.columns:
        df = df.withColumn("sub", F.lit(0))
    df = df.withColumn("stream_id", F.col("stream_id").cast("string"))

    def make():
        def step(key: tuple, rows: pa.Table) -> pa.Table:
            cfg, window, sub = key
            x = matrix(rows, xs)
            out = impute_window(x if scaler is None else (x - scaler.mean) / scaler.scale, options[cfg], (window, sub), stream_codes(rows), times_of(rows))
            gone = np.isnan(x)
            made = out.x if scaler is None else np.where(gone, out.x * scaler.scale + scaler.mean, x)
            bits = pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1) * len(xs), pa.int32()), pa.array(gone.ravel()))
            return result(rows, xs, made, out, {"cfg": pa.array(np.full(rows.num_rows, cfg), pa.int32())}, is_imputed=bits)

        return step

    schema = f"cfg int, window_id long, stream_id string, inst_id long, {', '.join(f'{c} double' for c in xs)}, is_imputed array<boolean>, {STATS}"
    keys = ["cfg", "window_id", "sub"]
    return by_group(df.select(*keys, "stream_id", "inst_id", *xs), keys, keys, ["inst_id"], make, schema)


def snapshot(df: DataFrame, method: str = "propnet", *, scale: bool = True, max_rows: int | None = None, **settings) -> DataFrame:
    """df with every missing cell filled and is_imputed, a bit for each attribute; observed cells stay to the bit. One
    shuffle: the cells that were there go through the kernel with the rest. One row for each row of df, repeated and
    null ids included. Windows are whole at every size; with max_rows, larger ones are split for every method but the
    mean, which is an aggregation (scaling does not change it)."""
    xs = attributes(df)
    if method == "mean":
        return _window_means(df)
    work = windows.split(df, max_rows) if max_rows else df
    out = run_windows(work, {0: Options(method=method, **settings)}, Scaler.fit(df) if scale else None)
    return out.select("window_id", "stream_id", "inst_id", *xs, "is_imputed")


def _window_means(df: DataFrame) -> DataFrame:
    xs = attributes(df)
    seen = df.select("window_id", F.col("stream_id").cast("string").alias("stream_id"), "inst_id", *(F.when(~F.isnan(F.col(c).cast("double")), F.col(c).cast("double")).alias(c) for c in xs))
    mean = seen.groupBy(F.col("window_id").alias("m_window")).agg(*(F.coalesce(F.avg(c), F.lit(0.0)).alias(f"u{c[1:]}") for c in xs))
    out = seen.join(mean, F.col("window_id").eqNullSafe(F.col("m_window")))
    return out.select("window_id", "stream_id", "inst_id", *(F.coalesce(c, f"u{c[1:]}").alias(c) for c in xs), F.array(*(F.col(c).isNull() for c in xs)).alias("is_imputed"))


def known(settings: dict) -> dict:
    names = {f.name for f in fields(Options)}
    return {k: v for k, v in settings.items() if k in names}
