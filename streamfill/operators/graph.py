"""Similarity graphs as edge tables (window_id, src, dst, dist), on filled chunks.

`nearest`, `extremes` and `links` never make the pairs of a window as rows: rows with equal values are one class, the
classes of a window are dealt into blocks, and every pair of blocks is compared in one task as matrices. `pairs` is the
plain form for the distances themselves; it makes as many rows as its windows have squared, and is for windows of that
size.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from streamfill.schema import attributes
from streamfill.sources.durable import settle


def distance(left: str, right: str, xs: list[str], metric: str = "euclidean") -> Column:
    """Squared Euclidean distance (which orders alike), or one less the cosine; a row of zeros is at distance 1."""
    a, b = [F.col(f"{left}.{c}") for c in xs], [F.col(f"{right}.{c}") for c in xs]
    total = lambda terms: sum(terms[1:], terms[0])
    if metric == "euclidean":
        return total([(p - q) * (p - q) for p, q in zip(a, b, strict=True)])
    dot, na, nb = total([p * q for p, q in zip(a, b, strict=True)]), total([p * p for p in a]), total([q * q for q in b])
    return F.when((na == 0) | (nb == 0), F.lit(1.0)).otherwise(1 - dot / (F.sqrt(na) * F.sqrt(nb)))


def pairs(filled: DataFrame, metric: str = "euclidean") -> DataFrame:
    """Every ordered pair of different rows of a window."""
    xs = attributes(filled)
    own = filled.select("window_id", "inst_id", *xs)
    a, b = own.alias("a"), own.alias("b")
    joined = a.join(b, (F.col("a.window_id") == F.col("b.window_id")) & (F.col("a.inst_id") != F.col("b.inst_id")))
    return joined.select(F.col("a.window_id").alias("window_id"), F.col("a.inst_id").alias("src"), F.col("b.inst_id").alias("dst"), distance("a", "b", xs, metric).alias("dist"))


#: Different rows of a window in a block, about.
BLOCK_ROWS = 4096
#: Rows of a block compared at a time, so that a strip of distances stays in a core's cache.
STRIP_ROWS = 64


def classes(filled: DataFrame, keep: int = 1) -> DataFrame:
    """The different rows of each window (window_id, rep, ids, n, x...): rep is the least id of the rows with these
    values, ids the `keep` least in order, n their number. Rows with equal values are at the same distances, so pairs
    are compared once for each pair of classes; the rows of a class, however many, are only counted. Settled."""
    xs = attributes(filled)
    by = ["window_id", *xs]
    own = filled.select("window_id", "inst_id", *((F.col(c) + 0.0).alias(c) for c in xs))
    counted = own.groupBy(*by).agg(F.count("*").alias("n"), F.min("inst_id").alias("rep"))
    if keep == 1:
        return settle(counted.select("window_id", "rep", F.array("rep").alias("ids"), "n", *xs))
    place = F.row_number().over(Window.partitionBy(*by).orderBy("inst_id"))
    least = own.withColumn("place", place).where(F.col("place") <= keep).groupBy(*by).agg(F.array_sort(F.collect_list("inst_id")).alias("ids"))
    return settle(counted.join(least, by).select("window_id", "rep", "ids", "n", *xs))


def compare(kinds: DataFrame, step, schema: str, metric: str = "euclidean", block_rows: int = BLOCK_ROWS, once: bool = False) -> DataFrame:
    """Every pair of classes compared as matrices: a window is dealt into blocks, and step(window, d, q, c, q_n, c_n) is
    called with the distances of some rows q of a block to all rows c of another, ids and row numbers beside; it gives a
    table or None. With `once`, of a pair of blocks only one order is compared. Exact at every size: b blocks are b * b
    tasks, to each of which two blocks go."""
    import numpy as np
    import pyarrow as pa

    from streamfill.plans.groups import by_group

    xs = attributes(kinds)
    n = kinds.groupBy("window_id").agg(F.ceil(F.count("*") / block_rows).cast("int").alias("blocks"))
    own = kinds.select("window_id", F.col("rep").alias("inst_id"), "n", *xs).join(n, "window_id")
    own = own.withColumn("block", F.pmod(F.xxhash64("inst_id"), F.col("blocks")).cast("int"))
    every = F.sequence(F.lit(0), F.col("blocks") - 1)
    asks = F.transform(every, lambda b: F.struct(F.col("block").alias("i"), b.alias("j"), F.lit(0).alias("role")))
    answers = F.transform(every, lambda b: F.struct(b.alias("i"), F.col("block").alias("j"), F.lit(1).alias("role")))
    dealt = own.withColumn("to", F.explode(F.concat(asks, answers))).select("window_id", "to.i", "to.j", "to.role", "inst_id", "n", *xs)
    if once:
        dealt = dealt.where("i <= j")

    def gaps(a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Distances, in the order of operations that SQL would take, summed in place."""
        out = None
        for d in range(len(xs)):
            term = np.subtract.outer(a[:, d], b[:, d]) if metric == "euclidean" else np.multiply.outer(a[:, d], b[:, d])
            if metric == "euclidean":
                term *= term
            out = term if out is None else np.add(out, term, out=out)
        if metric == "euclidean":
            return out
        na, nb = (np.sqrt(sum((v[:, d] ** 2 for d in range(1, len(xs))), v[:, 0] ** 2)) for v in (a, b))
        np.divide(out, np.multiply.outer(np.where(na > 0, na, 1), np.where(nb > 0, nb, 1)), out=out)
        np.subtract(1, out, out=out)
        out[na == 0], out[:, nb == 0] = 1.0, 1.0
        return out

    def make():
        def both(key: tuple, rows: pa.Table) -> pa.Table | None:
            role = rows["role"].to_numpy()
            ids, x, size = rows["inst_id"].to_numpy(), np.column_stack([rows[c].to_numpy().astype(np.float64) for c in xs]), rows["n"].to_numpy()
            (q, c) = (role == r for r in (0, 1))
            if not q.any() or not c.any():
                return None
            made, q_ids, q_x, q_n = [], ids[q], x[q], size[q]
            for at in range(0, len(q_ids), STRIP_ROWS):
                some = slice(at, at + STRIP_ROWS)
                if (t := step(key[0], gaps(q_x[some], x[c]), q_ids[some], ids[c], q_n[some], size[c])) is not None:
                    made.append(t)
            return pa.concat_tables(made) if made else None

        return both

    keys = ["window_id", "i", "j"]
    return by_group(dealt, keys, keys, ["role", "inst_id"], make, schema)


def nearest(filled: DataFrame, k: int = 10, metric: str = "euclidean", block_rows: int = BLOCK_ROWS) -> DataFrame:
    """Each row's k nearest of its window (window_id, src, dst, dist, rank), ties by id. Ids must not repeat in a window.

    Of the k + 1 rows nearest to a class (itself included), ordered by distance and id, each belongs to one of the k + 1
    classes nearest by distance and least id, and is among the k + 1 least ids there. So b * (k + 1) candidates of a
    class are ranked, their ids put in, and each row takes that list without itself.
    """
    import numpy as np
    import pyarrow as pa

    xs = attributes(filled)
    kinds, top = classes(filled, k + 1), k + 1

    def step(window: int, d: np.ndarray, q_ids: np.ndarray, c_ids: np.ndarray, q_n: np.ndarray, c_n: np.ndarray) -> pa.Table:
        limit = np.partition(d, min(top, len(c_ids)) - 1, axis=1)[:, min(top, len(c_ids)) - 1]
        i, j = np.nonzero((d <= limit[:, None]) & np.isfinite(d))
        order = np.lexsort((c_ids[j], d[i, j], i))
        i, j = i[order], j[order]
        near = np.arange(len(i)) - np.searchsorted(i, np.arange(len(d)))[i] < top
        i, j = i[near], j[near]
        return pa.table({"window_id": pa.array(np.full(len(i), window), pa.int64()), "src": q_ids[i], "dst": c_ids[j], "dist": d[i, j]})

    found = compare(kinds, step, "window_id long, src long, dst long, dist double", metric, block_rows)
    order = Window.partitionBy("window_id", "src").orderBy("dist", "dst")
    found = found.withColumn("place", F.row_number().over(order)).where(F.col("place") <= top)
    found = found.join(kinds.select("window_id", F.col("rep").alias("dst"), "ids"), ["window_id", "dst"])
    near = F.transform("ids", lambda i: F.struct(F.col("dist"), i.alias("dst")))
    lists = found.groupBy("window_id", F.col("src").alias("rep")).agg(F.slice(F.array_sort(F.flatten(F.collect_list(near))), 1, top).alias("near"))
    lists = kinds.select("window_id", "rep", *xs).join(lists, ["window_id", "rep"]).drop("rep")
    own = filled.select("window_id", F.col("inst_id").alias("src"), *((F.col(c) + 0.0).alias(c) for c in xs))
    others = F.slice(F.filter("near", lambda e: e["dst"] != F.col("src")), 1, k)
    out = own.join(lists, ["window_id", *xs]).select("window_id", "src", F.posexplode(others).alias("at", "e"))
    return out.select("window_id", "src", "e.dst", "e.dist", (F.col("at") + 1).alias("rank"))


def extremes(filled: DataFrame, metric: str = "euclidean") -> DataFrame:
    """Of all ordered pairs of different rows of each window their number n, and the least and the most distance."""
    import numpy as np
    import pyarrow as pa

    kinds = classes(filled)

    def step(window: int, d: np.ndarray, q_ids: np.ndarray, c_ids: np.ndarray, q_n: np.ndarray, c_n: np.ndarray) -> pa.Table | None:
        alone = (q_ids[:, None] == c_ids[None, :]) & (q_n == 1)[:, None]
        if alone.all():
            return None
        return pa.table({"window_id": pa.array([window], pa.int64()), "least": [np.where(alone, np.inf, d).min()], "most": [np.where(alone, -np.inf, d).max()]})

    found = compare(kinds, step, "window_id long, least double, most double", metric, once=True).groupBy("window_id").agg(F.min("least").alias("least"), F.max("most").alias("most"))
    rows = kinds.groupBy("window_id").agg(F.sum("n").alias("n"))
    return rows.join(found, "window_id").select("window_id", (F.col("n") * (F.col("n") - 1)).alias("n"), "least", "most")


def links(filled: DataFrame, eps: float, metric: str = "euclidean") -> DataFrame:
    """The threshold graph by rows (window_id, inst_id, class_id, links): class_id is the least id of the rows with the
    same values, links the number of other rows, copies included, that are nearer than eps (not squared). Rows of one
    class have the same links; edges between copies are counted, not made."""
    import numpy as np
    import pyarrow as pa

    xs = attributes(filled)
    kinds, below = classes(filled), eps * eps if metric == "euclidean" else eps

    def step(window: int, d: np.ndarray, q_ids: np.ndarray, c_ids: np.ndarray, q_n: np.ndarray, c_n: np.ndarray) -> pa.Table:
        near = d < below
        itself = (near & (q_ids[:, None] == c_ids[None, :])).any(axis=1)
        found = near @ c_n - itself
        return pa.table({"window_id": pa.array(np.full(len(q_ids), window), pa.int64()), "rep": q_ids, "links": pa.array(found.astype(np.int64))})

    found = compare(kinds, step, "window_id long, rep long, links long", metric).groupBy("window_id", "rep").agg(F.sum("links").alias("links"))
    found = kinds.select("window_id", "rep", *xs).join(found, ["window_id", "rep"])
    own = filled.select("window_id", "inst_id", *((F.col(c) + 0.0).alias(c) for c in xs))
    return own.join(found, ["window_id", *xs]).select("window_id", "inst_id", F.col("rep").alias("class_id"), "links")


def knn(filled: DataFrame, k: int = 10, metric: str = "euclidean", mode: str = "union") -> DataFrame:
    """The neighbour graph, both directions of each edge: linked if either row is among the other's k nearest, or (mutual) if both are."""
    if mode not in ("union", "mutual"):
        raise ValueError("mode is union or mutual")
    ends = F.explode(F.array(F.struct("src", "dst"), F.struct(F.col("dst").alias("src"), F.col("src").alias("dst")))).alias("e")
    both = nearest(filled, k, metric).select("window_id", ends, "dist").groupBy("window_id", "e.src", "e.dst").agg(F.min("dist").alias("dist"), F.count("*").alias("n"))
    return (both if mode == "union" else both.where("n = 2")).drop("n")


def threshold(filled: DataFrame, eps: float, metric: str = "euclidean") -> DataFrame:
    """Edges below the distance eps (not squared). Euclidean: projections on the diagonal differ by no more than the
    rows do, so only rows in the same or the next strip of width eps are compared, and none is lost."""
    xs = attributes(filled)
    if metric != "euclidean":
        return _below_cosine(filled, eps)
    along = sum((F.col(c) for c in xs[1:]), F.col(xs[0])) / float(len(xs)) ** 0.5
    own = filled.select("window_id", "inst_id", *xs, F.floor(along / eps).cast("long").alias("strip"))
    near = own.withColumn("strip", F.explode(F.array(*(F.col("strip") + k for k in (-1, 0, 1)))))
    a, b = own.alias("a"), near.alias("b")
    same = (F.col("a.window_id") == F.col("b.window_id")) & (F.col("a.strip") == F.col("b.strip")) & (F.col("a.inst_id") != F.col("b.inst_id"))
    joined = a.join(b, same).select(F.col("a.window_id").alias("window_id"), F.col("a.inst_id").alias("src"), F.col("b.inst_id").alias("dst"), distance("a", "b", xs).alias("dist"))
    return joined.where(F.col("dist") < eps * eps)


def _below_cosine(filled: DataFrame, eps: float) -> DataFrame:
    """Of rows on the unit sphere the squared distance is twice the cosine distance, so the strips serve here too; they
    are a little wider than that, and the distance itself decides. A row of zeros is at distance 1 of all others."""
    xs = attributes(filled)
    if eps > 1:  # then the rows of zeros are near all, and strips cut nothing off
        return pairs(filled, "cosine").where(F.col("dist") < eps)
    length = F.sqrt(sum((F.col(c) * F.col(c) for c in xs[1:]), F.col(xs[0]) * F.col(xs[0])))
    unit = filled.withColumn("length", length).where("length > 0").select("window_id", "inst_id", *((F.col(c) / F.col("length")).alias(c) for c in xs))
    near = threshold(unit, (2 * eps) ** 0.5 * (1 + 1e-6) + 1e-9).select("window_id", "src", "dst")
    end = lambda side: filled.select("window_id", F.col("inst_id").alias(side), F.struct(*xs).alias("a" if side == "src" else "b"))
    both = near.join(end("src"), ["window_id", "src"]).join(end("dst"), ["window_id", "dst"])
    return both.select("window_id", "src", "dst", distance("a", "b", xs, "cosine").alias("dist")).where(F.col("dist") < eps)


def degrees(edges: DataFrame) -> DataFrame:
    return edges.groupBy("window_id", F.col("src").alias("inst_id")).agg(F.count("*").alias("degree"))


def normalise(edges: DataFrame, how: str = "sym") -> DataFrame:
    """Edges with weight w: 1 / sqrt(degree of src * degree of dst), or (row) 1 / degree of src. The edges are settled, as
    they are read up to three times."""
    edges = settle(edges.select("window_id", "src", "dst"))
    deg = degrees(edges)
    of = lambda end, name: deg.select("window_id", F.col("inst_id").alias(end), F.col("degree").alias(name))
    out = edges.select("window_id", "src", "dst").join(of("src", "ds"), ["window_id", "src"])
    if how == "row":
        return out.withColumn("w", 1.0 / F.col("ds")).drop("ds")
    return out.join(of("dst", "dd"), ["window_id", "dst"]).select("window_id", "src", "dst", (1.0 / F.sqrt((F.col("ds") * F.col("dd")).cast("double"))).alias("w"))


def stats(edges: DataFrame) -> DataFrame:
    """Nodes, edges and extreme degrees of each window's graph."""
    return degrees(edges).groupBy("window_id").agg(F.count("*").alias("nodes"), F.sum("degree").alias("edges"), F.min("degree").alias("least"), F.max("degree").alias("most"))


def histogram(edges: DataFrame) -> DataFrame:
    """How many nodes of each window have which degree."""
    return degrees(edges).groupBy("window_id", "degree").agg(F.count("*").alias("nodes"))


def components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """(window_id, inst_id, root): the least node that edges reach. Each round takes the least root among neighbours and
    that root's own root, so distances double; rounds are settled, and only whether one changed anything comes back."""
    edges = settle(edges.select("window_id", "src", "dst"))
    state = settle(edges.groupBy("window_id", F.col("src").alias("inst_id")).agg(F.least(F.first("src"), F.min("dst")).alias("root")))
    for _ in range(rounds):
        far = state.select("window_id", F.col("inst_id").alias("dst"), F.col("root").alias("near"))
        least = edges.join(far, ["window_id", "dst"]).groupBy("window_id", F.col("src").alias("inst_id")).agg(F.min("near").alias("near"))
        lower = state.join(least, ["window_id", "inst_id"]).withColumn("next", F.least("root", "near"))
        jump = state.select("window_id", F.col("inst_id").alias("next"), F.col("root").alias("far"))
        moved = settle(lower.join(jump, ["window_id", "next"]).select("window_id", "inst_id", F.least("next", "far").alias("root"), (F.least("next", "far") != F.col("root")).alias("moved")))
        state = moved.drop("moved")
        if not moved.where("moved").limit(1).count():
            return state
    raise ValueError(f"components did not settle in {rounds} rounds")


def energy(weighted: DataFrame, x: DataFrame) -> DataFrame:
    """Dirichlet energy of each window: weighted squared differences along edges."""
    xs = attributes(x)
    a = x.select("window_id", F.col("inst_id").alias("src"), *(F.col(c).alias(f"a{c[1:]}") for c in xs))
    b = x.select("window_id", F.col("inst_id").alias("dst"), *(F.col(c).alias(f"b{c[1:]}") for c in xs))
    gap = sum(((F.col(f"a{c[1:]}") - F.col(f"b{c[1:]}")) ** 2 for c in xs), F.lit(0.0))
    return weighted.join(a, ["window_id", "src"]).join(b, ["window_id", "dst"]).groupBy("window_id").agg(F.sum(F.col("w") * gap).alias("energy"))


def knn_lsh(filled: DataFrame, k: int = 10, tables: int = 6, width: float = 2.0, seed: int = 7) -> DataFrame:
    """Approximate neighbours: rows meet that share a bucket of some random projection, and are ranked exactly.

    Hot buckets are bounded by the width; recall is measured against `nearest` in the tests.
    """
    import numpy as np

    xs = attributes(filled)
    rng = np.random.default_rng(seed)
    plans = [(rng.standard_normal(len(xs)) / len(xs) ** 0.5, float(rng.uniform(0, width))) for _ in range(tables)]
    spread = lambda p, shift: F.floor((sum((F.col(c) * float(v) for c, v in zip(xs, p, strict=True)), F.lit(0.0)) + shift) / width).cast("long")
    own = filled.select("window_id", "inst_id", *xs, F.posexplode(F.array(*(spread(p, s) for p, s in plans))).alias("t", "bucket"))
    a, b = own.alias("a"), own.alias("b")
    meet = (F.col("a.window_id") == F.col("b.window_id")) & (F.col("a.t") == F.col("b.t")) & (F.col("a.bucket") == F.col("b.bucket")) & (F.col("a.inst_id") != F.col("b.inst_id"))
    found = a.join(b, meet).select(F.col("a.window_id").alias("window_id"), F.col("a.inst_id").alias("src"), F.col("b.inst_id").alias("dst"), distance("a", "b", xs).alias("dist")).distinct()
    order = Window.partitionBy("window_id", "src").orderBy("dist", "dst")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)
