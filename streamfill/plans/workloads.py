"""The experiment workloads over the fixtures, and the queries that no SQL expresses.

Scalers are fitted after cells are taken out, and all methods of a workload see the same scaler and the same removed
cells, so errors of different methods may be compared. A sweep over settings is one job over (setting, window).
"""

from __future__ import annotations

from dataclasses import replace
from functools import partial
from itertools import product

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from streamfill.functions import nets, sequence
from streamfill.operators import graph as edges
from streamfill.operators import masks, metrics, windows
from streamfill.operators.fill import Scaler
from streamfill.plans import continuous
from streamfill.plans.catalog import ORACLES
from streamfill.plans.groups import idle_cores
from streamfill.plans.impute import METHODS, Options, run_windows, seeded, snapshot
from streamfill.schema import attributes
from streamfill.sources.durable import settle
from streamfill.sources.tables import DAY, HOUR, fixture

#: As published.
EPOCHS = 200
BASE = Options(epochs=EPOCHS)


def prepared(df: DataFrame, rate: float, seed: int = 0) -> tuple[DataFrame, DataFrame]:
    """(scaled chunks without the removed cells, the removed cells on the same scale)."""
    left, gone = masks.remove_cells(df, rate, seed)
    scaler = Scaler.fit(left)
    one = lambda d: F.array(*map(F.lit, d))
    at = F.col("dim") + 1
    truth = (F.col("truth") - F.element_at(one(scaler.mean), at)) / F.element_at(one(scaler.scale), at)
    return scaler.transform(left), gone.withColumn("truth", truth)


def errors(gone: DataFrame, out: DataFrame, labels: dict[int, dict]) -> DataFrame:
    """A row for each setting: its labels, mean and relative error over windows and over all cells, and costs a window."""
    xs = attributes(out)
    vals = F.array(*(F.struct(F.lit(int(c[1:])).alias("dim"), F.col(c).alias("val")) for c in xs))
    flat = out.select("cfg", "window_id", "inst_id", F.explode(vals).alias("c")).select("cfg", "window_id", "inst_id", "c.dim", "c.val")
    gap, size = F.abs(F.col("truth") - F.col("val")), F.abs("truth")
    per = gone.join(flat, ["window_id", "inst_id", "dim"]).groupBy("cfg", "window_id").agg(F.avg(gap).alias("mae"), F.try_divide(F.sum(gap), F.sum(size)).alias("mre"), F.sum(gap).alias("gap"), F.sum(size).alias("size"), F.count("*").alias("n"))
    cost = out.groupBy("cfg", "window_id").agg(F.max("graph_s").alias("graph_s"), F.max("total_s").alias("total_s"), F.max("cached").alias("cached"), F.max("best_epoch").alias("best_epoch"), F.max("model_bytes").alias("model_bytes"))
    both = cost.join(per, ["cfg", "window_id"], "left").groupBy("cfg").agg(
        F.avg("mae").alias("mae"), F.avg("mre").alias("mre"), F.try_divide(F.sum("gap"), F.sum("size")).alias("mre_pooled"), F.try_divide(F.sum("size"), F.sum("n")).alias("magnitude"),
        F.sum("n").alias("n_cells"), F.count("*").alias("n_windows"), F.avg("graph_s").alias("graph_s"), F.avg("total_s").alias("seconds"),
        F.avg("cached").alias("cache_rows"), F.avg("best_epoch").alias("best_epoch"), (F.max("model_bytes") / 1e6).alias("model_mb"),
    )
    names = list(next(iter(labels.values())))
    rows = out.sparkSession.createDataFrame([(k, *map(str, v.values())) for k, v in labels.items()], "cfg int, " + ", ".join(f"{n} string" for n in names))
    return both.join(F.broadcast(rows), "cfg").select(*names, *both.columns[1:])


def sweep(df: DataFrame, rate: float, options: dict[int, Options], labels: dict[int, dict], seed: int = 0, shards: int = 1, alone: bool = False) -> DataFrame:
    """Settings over one fixture. The imputed rows are settled, for both errors and costs read them. alone: one setting
    after the other, so that the seconds of one are not those of its neighbours."""
    left, gone = prepared(df, rate, seed)
    left, gone = settle(left), settle(gone)
    chained = any(o.mode != "periodic" for o in options.values())
    run = lambda some: settle(continuous.run(left, some, shards) if chained else run_windows(left, some))
    out = union([run({k: o}) for k, o in options.items()]) if alone else run(options)
    return errors(gone, out, labels).withColumn("seed", F.lit(seed))


#: Results of the workloads that others read, by session, folder and name.
_kept: dict[tuple, DataFrame] = {}


def kept(spark: SparkSession, sf_dir: str, name: str, make) -> DataFrame:
    """make(), settled; a second call in the session reads the same table."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _kept:
        _kept[key] = settle(make())
    return _kept[key]


def union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def over(spark: SparkSession, sf_dir: str, fixtures: tuple, rates: tuple, options: list[tuple[dict, Options]], seed: int = 0, alone: bool = False, **more) -> DataFrame:
    """Every fixture at every rate under every setting."""
    parts = []
    for name in fixtures:
        df = fixture(spark, sf_dir, name, **more)
        for rate in rates if not isinstance(rates, dict) else rates[name]:
            parts.append(sweep(df, rate, {k: o for k, (_, o) in enumerate(options)}, {k: {"fixture": name, "rate": rate, **lab} for k, (lab, _) in enumerate(options)}, seed, alone=alone))
    return union(parts)


def methods(names: tuple = METHODS, base: Options = BASE) -> list[tuple[dict, Options]]:
    return [({"method": m}, replace(base, method=m)) for m in names]


RATES = {"ev": (0.1, 0.3, 0.5), "doc": (0.1, 0.3, 0.5), "lowrank": (0.1, 0.3, 0.5), "emb": (0.1, 0.3, 0.5), "li": (0.4, 0.6, 0.8), "roll": (0.1, 0.3, 0.5)}


def w1_effectiveness(spark, sf_dir, fixtures=("doc", "lowrank"), rates=RATES):
    """Errors of all methods by share removed."""
    return over(spark, sf_dir, fixtures, rates, methods())


def w1_effectiveness_sparse(spark, sf_dir):
    """The same on the sparse concurrent fixture, which holds no signal: no method should do much harm."""
    return over(spark, sf_dir, ("ev",), RATES, methods())


def w1_effectiveness_dense(spark, sf_dir):
    """The same on the dense heterogeneous fixture."""
    return over(spark, sf_dir, ("li",), RATES, methods())


def w1_effectiveness_wide(spark, sf_dir):
    return over(spark, sf_dir, ("emb",), RATES, methods())


def w2_time(spark, sf_dir, fixtures=("ev", "doc", "lowrank", "li", "emb")):
    """Seconds a window at the default rate, building the graph included."""
    return over(spark, sf_dir, fixtures, {name: RATES[name][-1:] for name in fixtures}, methods(), alone=True).select("fixture", "method", "graph_s", "seconds", "n_windows")


def w3_memory(spark, sf_dir):
    """Weights of the neural methods, as 32-bit numbers, over the windows of the given tables: of one window's model, and
    of all, each window having its own. They are made where a window's row lands."""
    import pyarrow as pa

    def weighed(name: str) -> DataFrame:
        df = fixture(spark, sf_dir, name)
        d = len(attributes(df))

        def step(batches):
            rng = seeded(0)
            for batch in batches:
                for method, make in (("propnet", lambda: nets.init(nets.Shape(d), rng)), ("brits", lambda: sequence.brits_weights(d, 32, rng)), ("saits", lambda: sequence.saits_weights(d, 32, rng))):
                    sizes = [nets.nbytes(make()) for _ in range(batch.num_rows)]
                    yield pa.RecordBatch.from_arrays([pa.array([method] * len(sizes), pa.string()), pa.array(sizes, pa.int64())], names=["method", "bytes"])

        made = df.groupBy("window_id").agg(F.count("*").alias("n")).mapInArrow(step, "method string, bytes long")
        return made.select(F.lit(name).alias("fixture"), F.lit(d).alias("dims"), "method", "bytes")

    each = union([weighed(name) for name in ("ev", "doc", "li", "lowrank", "emb")])
    return each.groupBy("fixture", "dims", "method").agg((F.max("bytes") / 1e6).alias("model_mb"), F.count("*").alias("n_windows"), (F.sum("bytes") / 1e6).alias("all_mb"))


SEQ = ("propnet", "fp", "brits", "saits")


LENGTHS = {
    "ev": (4 * HOUR, 8 * HOUR, 12 * HOUR, DAY, 2 * DAY, 3 * DAY), "li": (15 * DAY, 30 * DAY, 60 * DAY, 90 * DAY, 120 * DAY),
    "emb": (50, 100, 150, 200, 250), "roll": (8 * HOUR, DAY, 3 * DAY),
}
RATIOS = (0.01, *(k / 10 for k in range(1, 11)))


def w4_window_length(spark, sf_dir, lengths=LENGTHS):
    def make():
        parts = []
        for name, t in ((name, t) for name, ts in lengths.items() for t in ts):
            df = fixture(spark, sf_dir, name, window=t)
            parts.append(sweep(df, RATES[name][-1], dict(enumerate(o for _, o in methods(SEQ, BASE))), {k: {"fixture": name, "length": t, "method": m} for k, m in enumerate(SEQ)}, alone=True))
        return union(parts)

    return kept(spark, sf_dir, f"w4 {lengths}", make)


def w5_stream_ratio(spark, sf_dir, ratios=RATIOS, fixtures=("ev", "li", "roll"), names=SEQ):
    def make():
        parts = []
        for name, r in ((name, r) for name in fixtures for r in ratios):
            df = masks.keep_streams(fixture(spark, sf_dir, name), r, 1)
            parts.append(sweep(df, RATES[name][-1], dict(enumerate(o for _, o in methods(names, BASE))), {k: {"fixture": name, "ratio": r, "method": m} for k, m in enumerate(names)}, alone=True))
        return union(parts)

    return kept(spark, sf_dir, f"w5 {ratios} {fixtures} {names}", make)


def modes(base: Options) -> list[tuple[dict, Options]]:
    return [({"mode": m}, replace(base, mode=m)) for m in continuous.MODES[:4]]


def w6_continuous(spark, sf_dir, ratios=(0.01, 0.1, 1.0), rate=0.4, name="li"):
    """The four continuous modes by share of streams, after carrying by quantile, as scores on dense windows are small."""
    base = replace(BASE, eta=0.9, eta_mode="quantile")
    parts = []
    for r in ratios:
        df = masks.keep_streams(fixture(spark, sf_dir, name), r, 1)
        parts.append(sweep(df, rate, dict(enumerate(o for _, o in modes(base))), {k: {"ratio": r, **lab} for k, (lab, _) in enumerate(modes(base))}, alone=True))
    return union(parts)


def w7_irregular(spark, sf_dir, ratios=(0.001, 0.01, 0.1, 1.0), rate=0.5):
    parts = []
    for name, base in (("ev", replace(BASE, eta=0.25)), ("li", replace(BASE, eta=0.9, eta_mode="quantile"))):
        df = masks.irregular(fixture(spark, sf_dir, name), ratios, 9)
        parts.append(sweep(df, rate, dict(enumerate(o for _, o in modes(base))), {k: {"fixture": name, **lab} for k, (lab, _) in enumerate(modes(base))}))
    return union(parts)


def w8_absolute_errors(spark, sf_dir):
    """Absolute errors by window length and by ratio of streams, from the same runs as the relative ones."""
    a = w4_window_length(spark, sf_dir).select("fixture", F.lit("length").alias("axis"), F.col("length").alias("at"), "method", "mae")
    b = w5_stream_ratio(spark, sf_dir).select("fixture", F.lit("ratio").alias("axis"), F.col("ratio").alias("at"), "method", "mae")
    return a.unionByName(b)


def one(spark, sf_dir, settings: list[tuple[dict, Options]], name="doc", rate=0.3):
    return over(spark, sf_dir, (name,), (rate,), settings)


def w9_similarity(spark, sf_dir):
    base = [({"metric": m, "graph": "knn"}, replace(BASE, metric=m)) for m in ("euclidean", "cosine")]
    base += [({"metric": "euclidean", "graph": "mutual"}, replace(BASE, graph="mutual"))]
    base += [({"metric": m, "graph": f"below {e}"}, replace(BASE, metric=m, eps=e)) for m, e in (("euclidean", 1.0), ("cosine", 0.2))]
    return over(spark, sf_dir, ("doc", "li"), (0.3,), base)


def w10_neighbours(spark, sf_dir):
    return one(spark, sf_dir, [({"k": k}, replace(BASE, k=k)) for k in (2, 5, 10, 15, 20)])


def w11_layers(spark, sf_dir):
    return one(spark, sf_dir, [({"layers": n}, replace(BASE, layers=n)) for n in (1, 2, 3, 4)])


def w12_modules(spark, sf_dir):
    return one(spark, sf_dir, [({"module": m}, replace(BASE, module=m)) for m in ("sage", "gcn", "gat")])


def w13_importance_threshold(spark, sf_dir):
    base = replace(BASE, mode="dual_carry")
    settings = [({"eta": e, "by": "absolute"}, replace(base, eta=e)) for e in (0.05, *(k / 10 for k in range(1, 10)))]
    return one(spark, sf_dir, settings + [({"eta": e, "by": "quantile"}, replace(base, eta=e, eta_mode="quantile")) for e in (0.5, 0.9)])


def w14_losses(spark, sf_dir):
    return one(spark, sf_dir, [({"lams": lams}, replace(BASE, lams=lams)) for lams in ((1.0, 1.0), (0.0, 1.0), (1.0, 0.0))])


def w15_without_bound(spark, sf_dir):
    return one(spark, sf_dir, [({"bound": b}, replace(BASE, bound=b)) for b in (True, False)])


def w16_transfer(spark, sf_dir):
    base = replace(BASE, mode="model_carry")
    return one(spark, sf_dir, [({"update": u}, replace(base, update=u)) for u in continuous.UPDATES])


def w17_splitting(spark, sf_dir, sizes=(None, 500, 200), rate=0.4):
    parts = []
    for s in sizes:
        left, gone = prepared(fixture(spark, sf_dir, "li"), rate)
        left = left if s is None else windows.split(left, s)
        out = settle(run_windows(left, {0: BASE}))
        parts.append(errors(gone, out, {0: {"max_rows": s}}))
    return union(parts)


def w20_grid(spark, sf_dir, axes=None):
    """A full grid of settings over one fixture: metric, neighbours, layers, width and module together."""
    axes = axes or {"metric": ("euclidean", "cosine"), "k": (5, 10), "layers": (1, 2), "width": (None, 16), "module": ("sage", "gcn")}
    points = [dict(zip(axes, v, strict=True)) for v in product(*axes.values())]
    return one(spark, sf_dir, [(p, replace(BASE, **p)) for p in points], "lowrank")


def resume_gain(spark, sf_dir):
    """Seconds and epochs to the best, from scratch and from the last window's message weights, by window of the event
    fixture; one after the other, on the same rows."""
    df = fixture(spark, sf_dir, "ev")
    left = settle(Scaler.fit(df).transform(df))
    scratch, resumed = (settle(continuous.run(left, {0: replace(BASE, mode=m)}, side_by_side=False)) for m in ("periodic", "model_carry"))
    return metrics.resume_gain(scratch, resumed)


def w18_space(spark, sf_dir):
    """Cached rows by window for each way of carrying."""
    df = fixture(spark, sf_dir, "ev")
    settings = {0: Options(method="mean", mode="periodic"), 1: Options(method="mean", mode="dual_carry", eta=0.25), 2: Options(method="mean", mode="all")}
    out = continuous.run(df, settings)
    name = F.element_at(F.array(*map(F.lit, ("periodic", "dual_carry", "all"))), F.col("cfg") + 1)
    return out.groupBy(name.alias("mode"), "window_id").agg(F.count("*").alias("rows"), F.max("cached").alias("cached"))


def w19_hyperparameters(spark, sf_dir):
    """Weight decay and the loss's divisor, beyond the published setting; the choice is to be made on held-out cells only."""
    return one(spark, sf_dir, [({"decay": d, "norm": n}, replace(BASE, decay=d, norm=n)) for d in (0.1, 1e-2, 1e-3) for n in ("all", "observed")])


# --- single methods ------------------------------------------------------------------------------------------------
def _whole(name: str, **settings):
    def run(spark, sf_dir):
        return snapshot(fixture(spark, sf_dir, name), **settings)

    return run


def _mode(mode: str, **settings):
    def run(spark, sf_dir):
        df = fixture(spark, sf_dir, "ev")
        o = Options(mode=mode, epochs=EPOCHS, eta=0.25, **settings)
        out = continuous.run(Scaler.fit(df).transform(df), {0: o}, cores=idle_cores(spark, 1))
        return out.drop("cfg", "graph_s", "total_s")

    return run


def approximate_recall(spark, sf_dir):
    """Share of the exact neighbours that the approximate graph finds, by window."""
    df = fixture(spark, sf_dir, "lowrank")
    exact = edges.nearest(df, 10).select("window_id", "src", "dst")
    found = edges.knn_lsh(df, 10).select("window_id", "src", "dst", F.lit(1).alias("hit"))
    return exact.join(found, ["window_id", "src", "dst"], "left").groupBy("window_id").agg(F.avg(F.coalesce("hit", F.lit(0))).alias("recall"))


def propnet_distributed(spark, sf_dir, epochs=EPOCHS):
    """One window over all rows, trained with rows and edges as tables; each epoch costs two shuffles."""
    from streamfill.plans.graph_engine import fit_impute

    df = fixture(spark, sf_dir, "lowrank", window=1 << 40)
    left, _ = prepared(df, 0.3)
    return fit_impute(settle(left), Options(epochs=epochs))[0]


def stream_dual_carry(spark, sf_dir, epochs=25):
    """The events as a stream of files, windows imputed as the watermark closes them; the result is what came out."""
    import uuid

    from streamfill.sources import tables
    from streamfill.sources.durable import shared_folder
    from streamfill.streaming.live import live

    df = fixture(spark, sf_dir, "ev")
    scaler = Scaler.fit(df)
    xs = attributes(df)
    folder = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    # bring the instances into event time; a last row past the end closes the last window
    rows = df.withColumn("ts", F.timestamp_seconds(tables.bucket_of(F.col("inst_id")) * HOUR))
    last = rows.agg(F.max("window_id").alias("w")).select((F.col("w") + 2).alias("window_id"), F.lit("end").alias("stream_id"), F.lit(0).cast("long").alias("inst_id"), *(F.lit(None).cast("double").alias(c) for c in xs), F.timestamp_seconds((F.col("w") + 2) * DAY).alias("ts"))
    rows.unionByName(last).coalesce(1).write.parquet(f"{folder}/in")
    source = spark.readStream.schema(rows.schema).parquet(f"{folder}/in")
    out = live(source, Options(mode="dual_carry", epochs=epochs, eta=0.25), DAY, (scaler.mean, scaler.scale))
    query = out.writeStream.format("parquet").option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.parquet(f"{folder}/out")


_WORKLOADS = {k: f for k, f in globals().items() if k[:1] == "w" and k[1:2].isdigit()}
QUERIES = {}
QUERIES |= {f"propnet_{m}": _whole("doc", method="propnet", module=m, epochs=EPOCHS) for m in ("sage", "gcn", "gat")}
QUERIES |= {"propnet_ev": _whole("ev", method="propnet", epochs=EPOCHS), "mf": _whole("doc", method="mf"), "mice": _whole("doc", method="mice"), "mice_multiple": _whole("doc", method="mice", draws=3), "fp_converged": _whole("doc", method="fp", iters=200, tol=1e-6)}
QUERIES |= {"knn_nan": _whole("doc", method="knn", knn_metric="nan"), "brits": _whole("doc", method="brits"), "saits": _whole("doc", method="saits"), "mf_soft": _whole("lowrank", method="mf", shrink=0.5)}
QUERIES |= {m: _mode(m) for m in continuous.MODES[:4]} | {"cache_all": _mode("all", method="mf")} | {"approximate_recall": approximate_recall, "propnet_distributed": propnet_distributed, "resume_gain": resume_gain, "stream_dual_carry": partial(stream_dual_carry, epochs=EPOCHS)}
#: Those that take long are last, w8 after the two whose runs it reads.
_LONG = ("w1_effectiveness_wide", "w7_irregular", "w6_continuous", "w1_effectiveness_dense", "w2_time", "w4_window_length", "w5_stream_ratio", "w8_absolute_errors")
QUERIES |= {k: f for k, f in _WORKLOADS.items() if k not in _LONG} | {k: _WORKLOADS[k] for k in _LONG}

#: Sizes by formula: two layers of three matrices; two ways; two blocks; 4 bytes a number. Windows by what the tables hold.
ORACLES["w3_memory"] = """
    WITH v AS (
        SELECT 'ev' AS fixture, 5 AS dims, count(DISTINCT floor(epoch(ts) / 86400)) AS n FROM events
        UNION ALL SELECT 'doc', 8, count(DISTINCT floor(doc_id / 250)) FROM documents
        UNION ALL SELECT 'li', 11, count(DISTINCT floor(epoch(l_shipdate) / 2592000)) FROM lineitem JOIN part ON p_partkey = l_partkey JOIN orders ON o_orderkey = l_orderkey
        UNION ALL SELECT 'lowrank', 16, count(DISTINCT floor(vec_id / 150)) FROM embeddings
        UNION ALL SELECT 'emb', 64, count(DISTINCT floor(vec_id / 150)) FROM embeddings
    ), s AS (SELECT *, CAST(greatest(32, 2 * dims) AS BIGINT) AS f, 32 AS h FROM v), b AS (
        SELECT fixture, dims, n, 'propnet' AS method, 2 * (3 * dims * f + f + dims) * 4 AS bytes FROM s
        UNION ALL SELECT fixture, dims, n, 'brits', 2 * (4 * dims * h + 4 * dims * dims + h * h + 2 * h + 4 * dims) * 4 FROM s
        UNION ALL SELECT fixture, dims, n, 'saits', (2 * (3 * dims * h + 8 * h * h + 3 * h + dims) + 2 * dims * dims + dims) * 4 FROM s
    ) SELECT fixture, dims, method, bytes / 1e6 AS model_mb, n AS n_windows, n * bytes / 1e6 AS all_mb FROM b
"""
