"""Exact top-k by inner product, term at a time.

Vectors are rounded down to integers. Candidates are dealt into blocks, queries into batches; every pair of block
and batch is scored by itself. In a block each dimension is a posting list: the rows where it is not zero, and
their weights. A batch of queries goes through its dimensions and adds weight times posting to its score arrays;
then the k best of the block are picked by partition, and the picks of all blocks are merged.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Components in a block of candidates and in a batch of queries, on average; they bound a task's memory.
BLOCK, BATCH = 1 << 19, 1 << 18
#: Queries and candidates whose scores are held at once.
TILE = (64, 4096)


def quantised(vector: Column, scale: int = 256) -> Column:
    """floor(scale * x) of each component, as a long; null for a vector that is null, empty, or has a component that is
    null or not finite. A component beyond 64 bits raises an error."""
    bad = F.exists(vector, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == F.lit(float("inf"))))
    whole = F.transform(vector, lambda x: F.floor(x.cast("double") * scale))
    most = F.array_max(F.transform(vector, lambda x: F.abs(x.cast("double") * scale)))
    return F.when(~bad & (F.size(vector) > 0), F.when(most < float(1 << 63), whole).otherwise(F.raise_error(F.lit("a scaled component does not fit into 64 bits")).cast("array<bigint>")))


def postings(block: np.ndarray) -> list[tuple[np.ndarray | None, np.ndarray]]:
    """For each dimension (rows, weights); rows is None where most rows have a weight, and zeros are then kept."""
    out = []
    for d in range(block.shape[1]):
        column = np.ascontiguousarray(block[:, d])
        rows = np.flatnonzero(column)
        out.append((None, column) if 2 * len(rows) > len(column) else (rows, column[rows]))
    return out


def best(ids: np.ndarray, scores: np.ndarray, k: int) -> np.ndarray:
    """Places of the k highest scores; ids ascend, so among equal scores the first places win."""
    if len(scores) <= k:
        return np.lexsort((ids, -scores))
    least = np.partition(scores, len(scores) - k)[len(scores) - k]
    above = np.flatnonzero(scores > least)
    level = np.flatnonzero(scores == least)[: k - len(above)]
    picked = np.concatenate([above, level])
    return picked[np.lexsort((ids[picked], -scores[picked]))]


def score_block(q_ids: np.ndarray, q: np.ndarray, c_ids: np.ndarray, c: np.ndarray, k: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(query's place, places of its k best candidates here, their scores); a candidate with the query's id is left out."""
    largest = [max(map(abs, (int(x.min(initial=0)), int(x.max(initial=0))))) for x in (q, c)]
    if largest[0] * largest[1] * c.shape[1] >= 1 << 63:
        q, c = q.astype(object), c.astype(object)  # whole numbers of any size: slow, and exact
    for start in range(0, len(c_ids), TILE[1]):
        ids = c_ids[start : start + TILE[1]]
        lists = postings(c[start : start + TILE[1]])
        for first in range(0, len(q_ids), TILE[0]):
            some = q[first : first + TILE[0]]
            scores = np.zeros((len(some), len(ids)), dtype=c.dtype)
            for d, (rows, weights) in enumerate(lists):
                using = np.flatnonzero(some[:, d])
                if not len(using) or not len(weights):
                    continue
                add = some[using, d][:, None] * weights[None, :]
                if rows is not None:
                    scores[np.ix_(using, rows)] += add
                elif len(using) == len(some):
                    scores += add
                else:
                    scores[using] += add
            for i, row in enumerate(scores):
                own = ids != q_ids[first + i]
                if own.all():
                    at = best(ids, row, k)
                else:
                    others = np.flatnonzero(own)
                    at = others[best(ids[others], row[others], k)]
                yield first + i, start + at, row[at]


def _matrix(column: pa.ChunkedArray, width: int) -> np.ndarray:
    column = column.combine_chunks()
    if isinstance(column, pa.ChunkedArray):
        column = pa.concat_arrays(column.chunks)
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.int64).reshape(-1, width)


def top_k(vectors: DataFrame, is_query: Column, k: int = 5, *, id_col: str = "vec_id", vector_col: str = "embedding", scale: int = 256, block: int | None = None, batch: int | None = None) -> DataFrame:
    """Rows (query_id, rank, vec_id, score): for each query row its k best other rows, ties to the smaller vec_id.

    Vectors that are null, empty or hold null or non-finite components take no part, nor do rows with a null id.
    Vectors are compared with those of their own length. A row is never its query's candidate if it has the
    query's id; where an id repeats, rows alike count once as query and each as candidate. Scores are exact; a
    component, or a score among the k best, beyond 64 bits raises an error. An empty table gives an empty result;
    other columns are ignored.
    """
    all_rows = vectors.select(F.col(id_col).cast("long").alias("vec_id"), quantised(F.col(vector_col), scale).alias("code"), is_query.alias("asks"))
    rows = all_rows.where("vec_id is not null and code is not null").withColumn("width", F.size("code"))
    asked = rows.where("asks").select(F.col("vec_id").alias("query_id"), "code", "width").distinct()
    n, widest = rows.agg(F.count("*"), F.max("width")).first()
    blocks = max(1, math.ceil(n / (block or max(64, BLOCK // (widest or 1)))))
    batches = max(1, math.ceil(asked.count() / (batch or max(64, BATCH // (widest or 1)))))
    to_all = lambda n: F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n - 1).cast("long")))
    left = rows.select("vec_id", "code", "width", F.pmod(F.xxhash64("vec_id", F.lit(1)), F.lit(blocks)).alias("b"), to_all(batches).alias("q"))
    right = asked.select("query_id", F.xxhash64("code").alias("twin"), "code", "width", to_all(blocks).alias("b"), F.pmod(F.xxhash64("query_id", F.lit(2)), F.lit(batches)).alias("q"))

    def scored(candidates: pa.Table, queries: pa.Table) -> pa.Table:
        if not candidates.num_rows or not queries.num_rows:
            return pa.table({x: pa.array([], y) for x, y in (("query_id", pa.int64()), ("twin", pa.int64()), ("vec_id", pa.int64()), ("score", pa.int64()))})
        candidates = candidates.sort_by("vec_id")
        width = candidates["width"][0].as_py()
        c_ids, q_ids = candidates["vec_id"].to_numpy(), queries["query_id"].to_numpy()
        q = _matrix(queries["code"], width)
        twin = queries["twin"].to_numpy()
        found = [(np.full(len(at), q_ids[i]), np.full(len(at), twin[i]), c_ids[at], s) for i, at, s in score_block(q_ids, q, c_ids, _matrix(candidates["code"], width), k)]
        return pa.table({x: pa.array(np.concatenate(y).tolist() if y[0].dtype == object else np.concatenate(y), pa.int64()) for x, y in zip(("query_id", "twin", "vec_id", "score"), zip(*found, strict=True), strict=True)})

    keys = ["b", "q", "width"]
    picks = left.groupBy(*keys).cogroup(right.groupBy(*keys)).applyInArrow(scored, "query_id long, twin long, vec_id long, score long")
    order = Window.partitionBy("query_id", "twin").orderBy(F.desc("score"), F.asc("vec_id"))
    return picks.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
