"""Continuous imputation: what goes from one window to the next.

periodic carries nothing, so all windows run side by side. data_carry adds to a window the rows of earlier ones that
are worth most; model_carry starts from the last window's message weights; dual_carry does both; all keeps every row
so far. Which rows are carried follows from what is observed alone: where only rows are carried, a quick pass through
a shard's windows in order deals every window its cache, and the windows then run side by side. Where weights are
carried, a chain goes through them in order and holds one window, its cache and one set of weights.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from streamfill.functions import kernels
from streamfill.plans.groups import by_group
from streamfill.plans.impute import STATS, Options, impute_window, matrix, result, run_windows, stream_codes, times_of
from streamfill.schema import attributes

MODES = ("periodic", "data_carry", "model_carry", "dual_carry", "all")
UPDATES = ("message", "all", "frozen", "none")


def worth_keeping(x: np.ndarray, o: Options) -> np.ndarray:
    """Places of the rows that go into the next cache, all that score eta or more.
    With max_cache, at most so many: the most important and then the latest first.
    Rows that observe nothing are never kept."""
    seen = ~np.isnan(x)
    phi = kernels.importance(seen)
    eta = np.quantile(phi, o.eta) if o.eta_mode == "quantile" and len(phi) else o.eta
    kept = np.flatnonzero((phi >= eta) & seen.any(axis=1))
    if o.max_cache is not None and len(kept) > o.max_cache:
        kept = np.sort(kept[np.lexsort((-kept, -phi[kept]))[: o.max_cache]])
    return kept


def next_state(theta: dict | None, o: Options) -> dict | None:
    """The weights a following window starts from: message weights by default, all, or none."""
    if theta is None or o.update == "none":
        return None
    return theta if o.update == "all" else {k: v for k, v in theta.items() if k.startswith("msg")}


class Chain:
    """One shard's way through its windows."""

    def __init__(self, o: Options, shard: int = 0, cores: int = 1) -> None:
        self.o, self.shard, self.cores = o, shard, cores
        self.cache: tuple[np.ndarray, np.ndarray, np.ndarray] | None = None
        self.theta: dict | None = None

    def step(self, window: int, x: np.ndarray, streams: np.ndarray, times: np.ndarray):
        """(outcome over the rows given, cached rows used). The cache and the rows are scored together, raw; both train
        the network, and only the rows given come out."""
        o, cached = self.o, 0
        both = (x, streams, times)
        if self.cache is not None and o.mode in ("data_carry", "dual_carry", "all"):
            cached = len(self.cache[0])
            both = tuple(np.concatenate([c, r]) for c, r in zip(self.cache, both, strict=True))
        start = self.theta if o.mode in ("model_carry", "dual_carry") else None
        out = impute_window(both[0], o, (window, self.shard), both[1], both[2], start, self.cores)
        out.x = out.x[cached:]
        if o.mode in ("model_carry", "dual_carry"):
            self.theta = next_state(out.theta, o)
        if o.mode == "all":
            self.cache = both
        elif o.mode in ("data_carry", "dual_carry"):
            keep = worth_keeping(both[0], o)
            self.cache = tuple(c[keep] for c in both)
        return out, cached


def deal_caches(df: DataFrame, options: dict[int, Options]) -> DataFrame:
    """Rows of (cfg, shard, window_id) with those that the shard's earlier windows leave it: place numbers a window's rows,
    those carried first, and `cached` says how many these are. df: rows with cfg and shard."""
    xs = attributes(df)
    plain = ["stream_id", "inst_id", *xs]

    def make():
        held: dict[tuple, pa.Table] = {}

        def step(key: tuple, rows: pa.Table) -> pa.Table:
            cfg, shard, window = key
            own = rows.select(plain)
            if (cfg, shard) not in held:
                held.clear()
                held[cfg, shard] = own.slice(0, 0)
            cache = held[cfg, shard]
            both = pa.concat_tables([cache, own]).combine_chunks()
            o = options[cfg]
            held[cfg, shard] = both if o.mode == "all" else both.take(pa.array(worth_keeping(matrix(both, xs), o)))
            same = lambda v, t: pa.array(np.full(both.num_rows, v), t)
            head = {"cfg": same(cfg, pa.int32()), "shard": same(shard, pa.int32()), "window_id": same(window, pa.int64()), "place": pa.array(np.arange(both.num_rows), pa.int32()), "cached": same(cache.num_rows, pa.int32())}
            return pa.table(head | {c: both[c] for c in plain})

        return step

    schema = f"cfg int, shard int, window_id long, place int, cached int, stream_id string, inst_id long, {', '.join(f'{c} double' for c in xs)}"
    return by_group(df.select("cfg", "shard", "window_id", *plain), ["cfg", "shard"], ["cfg", "shard", "window_id"], ["inst_id"], make, schema)


def run_dealt(dealt: DataFrame, options: dict[int, Options]) -> DataFrame:
    """The windows of deal_caches, side by side; only their own rows come out."""
    xs = attributes(dealt)

    def make():
        def step(key: tuple, rows: pa.Table) -> pa.Table:
            cfg, shard, window = key
            n = rows["cached"][0].as_py()
            out = impute_window(matrix(rows, xs), options[cfg], (window, shard), stream_codes(rows), times_of(rows))
            out.x = out.x[n:]
            own = rows.slice(n)
            return result(own, xs, out.x, out, {"cfg": pa.array(np.full(own.num_rows, cfg), pa.int32())}, n)

        return step

    schema = f"cfg int, window_id long, stream_id string, inst_id long, {', '.join(f'{c} double' for c in xs)}, {STATS}"
    keys = ["cfg", "shard", "window_id"]
    return by_group(dealt, keys, keys, ["place"], make, schema)


def run(df: DataFrame, options: dict[int, Options], shards: int = 1, side_by_side: bool = True, cores: int = 1) -> DataFrame:
    """(cfg, keys, x..., figures) for every setting. One shard is the method as described; more are independent chains
    over groups of streams, which run side by side. Settings that carry no weights run their windows side by side too,
    unless that is turned off; the results are the same. cores: those that a chain's training may use where it lands, if
    nothing else runs there (`idle_cores`); the results are the same."""
    if all(o.mode == "periodic" for o in options.values()) and shards == 1:
        return run_windows(df, options).drop("is_imputed")
    kinds = [{k: o for k, o in options.items() if o.mode in modes} for modes in (("periodic",), ("data_carry", "all"), ("model_carry", "dual_carry"))]
    free = next(k for k in kinds if k)
    if side_by_side and len(free) < len(options):
        rest = {k: o for k, o in options.items() if k not in free}
        given = "cfg" in df.columns
        return run(df.where(F.col("cfg").isin(list(free))) if given else df, free, shards).unionByName(run(df.where(F.col("cfg").isin(list(rest))) if given else df, rest, shards))
    xs = attributes(df)
    if "cfg" not in df.columns:
        df = df.withColumn("cfg", F.explode(F.array(*(F.lit(k).cast("int") for k in options))))
    df = df.withColumn("stream_id", F.col("stream_id").cast("string"))
    df = df.withColumn("shard", F.pmod(F.xxhash64("stream_id"), F.lit(shards)).cast("int"))
    if side_by_side and free is kinds[1]:
        return run_dealt(deal_caches(df, free), free)

    def make():
        chains: dict[tuple, Chain] = {}

        def step(key: tuple, rows: pa.Table) -> pa.Table:
            cfg, shard, window = key
            if (cfg, shard) not in chains:
                chains.clear()  # groups come in order: the chain before is over
                chains[cfg, shard] = Chain(options[cfg], shard, cores)
            out, cached = chains[cfg, shard].step(window, matrix(rows, xs), stream_codes(rows), times_of(rows))
            return result(rows, xs, out.x, out, {"cfg": pa.array(np.full(rows.num_rows, cfg), pa.int32())}, cached)

        return step

    schema = f"cfg int, window_id long, stream_id string, inst_id long, {', '.join(f'{c} double' for c in xs)}, {STATS}"
    return by_group(df.select("cfg", "shard", "window_id", "stream_id", "inst_id", *xs), ["cfg", "shard"], ["cfg", "shard", "window_id"], ["inst_id"], make, schema)
