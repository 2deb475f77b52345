"""Operator 6: exact top-k search by sequential reads of sorted lists only.

Vectors and queries are dealt to blocks by hash, and each pair of a block of queries and one of vectors is one task's group, so that neither
side passes the driver. A task keeps one list a dimension for some vectors at a time, sorted by component. For a query the lists
are read from the end that its sign prefers, to twice the depth each time; each entry read adds its product to its vector's sum and
nothing else of the vectors is touched. What was read gives each vector a lower bound (unread components at their least) and an upper
bound (unread ones at the value that the list has come to); a vector that no list has shown yet has the sum of these values. Reading
stops when all vectors outside a small set have upper bounds below the k-th lower bound, or below the k-th score that earlier lists
gave; the set's final scores are then resolved exactly, ties included. k rows for each query and block of vectors are shuffled.

Components become floor(1024 * x), scores are sums of products of such integers, resolved in whole numbers where they could pass 2**53, and
held to the range of a long.

Defined results: null vectors and vectors with null, NaN or infinite components take no part, neither do null ids; components beyond the
range of a long are held to it; vectors of other lengths than the query's count as padded with zeros; rows that repeat a vec_id are
candidates of their own and, as queries, one query each id (the first in the order of components); a query never meets rows of its
own id; an empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import cut_lineage, spread, table

TOP, SCALE, QUERY_STEP = 10, 1024, 100
#: Queries and vectors of a task's group; vectors whose lists are kept at a time; vectors left to resolve when reading may stop, as a multiple of k.
QUERY_BLOCK, VECTOR_BLOCK, LISTS, RESOLVE = 8192, 65_536, 8192, 32


def quantised(df: DataFrame, id_col: str = "vec_id", vector: str = "embedding", scale: int = SCALE) -> DataFrame:
    """(vec_id, v): integer components of the vectors that take part."""
    x = F.transform(F.col(vector), lambda c: c.cast("double"))
    df = df.select(F.col(id_col).cast("long").alias("vec_id"), x.alias("x")).filter("vec_id is not null and x is not null")
    df = df.filter(~F.exists("x", lambda c: c.isNull() | F.isnan(c) | (F.abs(c) == float("inf"))))
    return df.select("vec_id", F.transform("x", lambda c: F.floor(c * scale)).alias("v"))


class SortedLists:
    """The sorted lists of some vectors: order[j] holds the rows in rising order of component j, sorted[j] the components."""

    def __init__(self, ids: np.ndarray, x: np.ndarray):
        self.ids, self.x = ids, x
        order = np.argsort(x, axis=0, kind="stable")
        self.order, self.sorted = np.ascontiguousarray(order.T.astype(np.int32)), np.ascontiguousarray(np.take_along_axis(x, order, axis=0).T)
        self.largest = float(np.abs(x).max()) if x.size else 0.0
        self.seen = np.zeros(self.order.shape, dtype=np.float32)

    def scores(self, rows: np.ndarray, query: np.ndarray) -> np.ndarray:
        """Inner products as longs."""
        if self.largest * float(np.abs(query).sum()) < 2**53:
            return (self.x[rows] @ query).astype(np.int64)
        whole = [int(c) for c in query]
        sums = (sum(int(a) * b for a, b in zip(self.x[i].tolist(), whole, strict=True)) for i in rows)
        return np.array([max(-(2**63), min(2**63 - 1, s)) for s in sums], dtype=np.int64)

    def search(self, query: np.ndarray, own: int, k: int, floor: float, resolve: int = RESOLVE, first: int | None = None) -> tuple[np.ndarray, np.ndarray, int]:
        """(ids, scores) of all vectors that can be among the k best, given that k scores of floor or more are known elsewhere, and the depth read."""
        n, d = self.x.shape
        others = self.ids != own
        used = np.flatnonzero(query)
        if n == 0 or not len(used):
            rows = np.flatnonzero(others)
            return self.ids[rows], np.zeros(len(rows), dtype=np.int64), 0
        up, down = np.flatnonzero(query < 0), np.flatnonzero(query > 0)  # lists read from their least and from their greatest
        got, seen = np.zeros(n), self.seen
        seen[:] = 0
        worst = np.zeros(d)
        worst[up], worst[down] = self.sorted[up, -1] * query[up], self.sorted[down, 0] * query[down]
        ahead = np.zeros(d)
        at, to = 0, min(n, first or max(64, n // 8))
        while True:
            for lists, part in ((up, slice(at, to)), (down, slice(n - to, n - at))):
                rows = self.order[lists, part]
                got += np.bincount(rows.ravel(), weights=(self.sorted[lists, part] * query[lists, None]).ravel(), minlength=n)
                seen[lists[:, None], rows] = 1
            at = to
            ahead[up], ahead[down] = self.sorted[up, at - 1] * query[up], self.sorted[down, n - at] * query[down]
            read = np.column_stack([ahead, worst]).astype(np.float32).T @ seen
            upper, lower = got + (ahead.sum() - read[0]), got + (worst.sum() - read[1])
            loose = 1 + 1e-5 * np.abs([ahead, worst]).sum()  # more than what single precision loses
            best = max(floor, np.partition(lower[others], -k)[-k] - loose if others.sum() >= k else -np.inf)
            best = -np.inf if best < -(2.0**63) else min(best, 2.0**63)  # beyond a long all scores are equal
            left = others & (upper >= best - loose)
            if at == n or left.sum() <= resolve * k:
                rows = np.flatnonzero(left)
                return self.ids[rows], self.scores(rows, query), at
            to = min(n, 2 * at)


def _block(vectors: list, dims: int) -> np.ndarray:
    out = np.zeros((len(vectors), dims))
    for i, v in enumerate(vectors):
        out[i, : min(dims, len(v))] = v[:dims]
    return out


def _searcher(k: int, lists: int):
    def run(queries: pd.DataFrame, vectors: pd.DataFrame) -> pd.DataFrame:
        """The k best of this block of vectors for each query of this block."""
        none = pd.DataFrame({c: pd.Series(dtype="int64") for c in ("query_id", "vec_id", "score")})
        if not len(queries) or not len(vectors):
            return none
        queries = queries.sort_values("vec_id")
        ids, q = queries["vec_id"].to_numpy(), _block(queries["v"].to_list(), max(map(len, queries["v"])))
        best = [(np.empty(0, dtype=np.int64), np.empty(0, dtype=np.int64))] * len(ids)
        for a in range(0, len(vectors), lists):
            some = vectors.iloc[a : a + lists]
            held = SortedLists(some["vec_id"].to_numpy(), _block(some["v"].to_list(), q.shape[1]))
            for i, own in enumerate(ids.tolist()):
                floor = float(best[i][1][-1]) if len(best[i][1]) == k else -np.inf
                found, scores, _ = held.search(q[i], own, k, floor)
                found, scores = np.concatenate([best[i][0], found]), np.concatenate([best[i][1], scores])
                top = np.lexsort((found, -scores.astype(np.longdouble)))[:k]
                best[i] = found[top], scores[top]
        made = [pd.DataFrame({"query_id": own, "vec_id": found, "score": scores}) for own, (found, scores) in zip(ids.tolist(), best, strict=True) if len(found)]
        return pd.concat(made, ignore_index=True) if made else none

    return run


def top_k(vectors: DataFrame, queries: DataFrame, k: int = TOP, query_block: int = QUERY_BLOCK, vector_block: int = VECTOR_BLOCK, lists: int = LISTS) -> DataFrame:
    """query_id, rank, vec_id, score. vectors and queries: (vec_id, v)."""
    asked = cut_lineage(queries.groupBy("vec_id").agg(F.min("v").alias("v")))
    total, cores = vectors.count(), vectors.sparkSession.sparkContext.defaultParallelism
    qs = spread(asked.count(), query_block)
    vs = max(spread(total, vector_block), min(2 * cores, spread(total, 2048)))  # smaller blocks where there are cores to spare
    every = lambda count: F.explode(F.sequence(F.lit(0), F.lit(count - 1)))
    of = lambda count: F.pmod(F.xxhash64("vec_id", F.lit(6)), F.lit(count)).cast("int")
    asked = asked.withColumn("qb", of(qs)).withColumn("vb", every(vs))
    held = vectors.select("vec_id", "v").withColumn("vb", of(vs)).withColumn("qb", every(qs))
    found = asked.groupBy("qb", "vb").cogroup(held.groupBy("qb", "vb")).applyInPandas(_searcher(k, lists), "query_id long, vec_id long, score long")
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return found.withColumn("rank", rank).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op6_topk(spark, sf_dir: str) -> DataFrame:
    vectors = quantised(table(spark, sf_dir, "embeddings"))
    return top_k(vectors, vectors.filter(F.col("vec_id") % QUERY_STEP == 0))


ORACLE = f"""WITH e AS (SELECT vec_id, list_transform(embedding, lambda x: floor({SCALE} * x::DOUBLE)::BIGINT) AS v FROM embeddings
WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.vec_id AS query_id, c.vec_id, list_sum(list_transform(list_zip(q.v, c.v), lambda p: p[1] * p[2]))::BIGINT AS score
FROM e q JOIN e c ON q.vec_id <> c.vec_id WHERE q.vec_id % {QUERY_STEP} = 0),
r AS (SELECT query_id, (row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id))::INTEGER AS rank, vec_id, score FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= {TOP}"""
