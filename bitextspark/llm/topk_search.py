"""Exact top-k inner product by multi-resolution segment statistics.

A vector is described at several resolutions by the mean and the deviation of
its segments. For a segment of w components, the inner product of two vectors
is at most w * (mean * mean + deviation * deviation), so from the coarsest
resolution to the finest a growing sum of statistics bounds the score from
above (for vectors of given norms that is a lower bound of their distance).
What a resolution cannot rule out goes on to the next; the survivors' scores
are computed exactly. A candidate is ruled out only if its bound lies below
the k-th score that the query has already, so ties survive.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut, tidy

RESOLUTIONS = (1, 4, 16)
#: Queries that are sent to the workers at a time.
QUERY_BLOCK = 16_384
#: Queries and candidates that are scored at a time within a task.
TILE_QUERIES, TILE_ROWS = 512, 4096
#: Share of a tile's pairs beyond which they are scored by one product.
DENSE = 0.3
K = 5


def usable(column: str) -> Column:
    """Whether a vector takes part: not null, not empty, all components finite."""
    x = F.col(column)
    return x.isNotNull() & (F.size(x) > 0) & F.forall(x, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf")))


def quantised(column: str, scale: int = 256) -> Column:
    return F.transform(F.col(column), lambda v: F.floor(v.cast("double") * scale).cast("double"))


def statistics(x: np.ndarray, segments: int) -> np.ndarray:
    """Rows (means, deviations) of x by segment, scaled so that a product of two rows bounds the inner product."""
    edges = np.linspace(0, x.shape[1], segments + 1).astype(int)
    out = []
    for a, b in zip(edges, edges[1:], strict=False):
        if b > a:
            part = x[:, a:b]
            mean = part.mean(axis=1)
            out += [mean * math.sqrt(b - a), np.sqrt(np.maximum((part * part).sum(axis=1) - (b - a) * mean * mean, 0.0))]
    return np.stack(out, axis=1)


class Searcher:
    """Keeps the k best of every query of a block over the candidates that it has been shown."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, k: int, resolutions=RESOLUTIONS):
        self.ids, self.vectors, self.k = ids, vectors, k
        self.levels = [(s, statistics(vectors, s)) for s in resolutions if s <= vectors.shape[1]]
        self.score = np.full((len(ids), k), -np.inf)
        self.best = np.full((len(ids), k), np.iinfo(np.int64).max)
        self.bounded = self.exact = 0

    def show(self, ids: np.ndarray, vectors: np.ndarray) -> None:
        mine = [(s, statistics(vectors, s)) for s, _ in self.levels]
        for a in range(0, len(self.ids), TILE_QUERIES):
            self._tile(slice(a, a + TILE_QUERIES), ids, vectors, mine)

    def _floor(self, at: np.ndarray) -> np.ndarray:
        """The k-th score so far of queries, a little lower against rounding."""
        floor = self.score[at, -1]
        return np.where(np.isfinite(floor), floor - 1e-6 * np.maximum(1, np.abs(floor)), -np.inf)[:, None]

    def _tile(self, rows: slice, ids: np.ndarray, vectors: np.ndarray, mine) -> None:
        at = np.arange(len(self.ids))[rows]
        alive = self.ids[at][:, None] != ids[None, :]
        self.bounded += alive.size
        floor, bound = self._floor(at), None
        for (_, a), (_, b) in zip(self.levels, mine, strict=True):
            bound = a[rows] @ b.T
            alive &= bound >= floor
            if not alive.any():
                return
        # each query's best bounds come first: their scores raise the floor for its other pairs
        some = min(4 * self.k, len(ids))
        if some < len(ids):
            best = np.argpartition(np.where(alive, bound, -np.inf), len(ids) - some, axis=1)[:, -some:]
            first = np.zeros_like(alive)
            np.put_along_axis(first, best, True, axis=1)
            first &= alive
            self._score(at, ids, vectors, first)
            alive &= ~first
            alive &= bound >= self._floor(at)
        self._score(at, ids, vectors, alive)

    def _score(self, at: np.ndarray, ids: np.ndarray, vectors: np.ndarray, alive: np.ndarray) -> None:
        """Exact scores of the pairs that are alive, merged into the best."""
        left = int(alive.sum())
        if not left:
            return
        if left > DENSE * alive.size:
            # a product of whole tiles is cheaper than gathering most pairs
            self.exact += alive.size
            scores = np.where(alive, self.vectors[at] @ vectors.T, -np.inf)
        else:
            self.exact += left
            scores = np.full(alive.shape, -np.inf)
            q, c = np.nonzero(alive)
            for a in range(0, left, 65_536):
                i, j = q[a : a + 65_536], c[a : a + 65_536]
                scores[i, j] = np.einsum("pd,pd->p", self.vectors[at[i]], vectors[j])
        # rows that the k-th score so far rules out are left out of the merge
        for i in np.flatnonzero((scores >= self.score[at, -1][:, None]).any(axis=1) & (scores > -np.inf).any(axis=1)):
            n, row = at[i], scores[i]
            near = np.flatnonzero(row >= self.score[n, -1]) if np.isfinite(self.score[n, -1]) else np.flatnonzero(row > -np.inf)
            if len(near) > 64 * self.k:
                kth = np.partition(row[near], len(near) - self.k)[len(near) - self.k]
                near = near[row[near] >= kth]
            s, v = np.concatenate([self.score[n], row[near]]), np.concatenate([self.best[n], ids[near]])
            order = np.lexsort((v, -s))[: self.k]
            self.score[n], self.best[n] = s[order], v[order]


def top_k(vectors: DataFrame, is_query: Column, id_col: str = "vec_id", vector_col: str = "embedding", k: int = K, scale: int = 256, resolutions=RESOLUTIONS, block: int = QUERY_BLOCK) -> DataFrame:
    """(query_id, rank, vec_id, score): the k highest integer inner products of each query over all rows but its own.

    Queries are the rows where is_query holds. They are sent out in blocks of a
    fixed size, each block is held against every row, and a task keeps k rows a
    query only, so neither driver nor tasks hold more than a block. Vectors
    that are null, empty or hold null or non-finite components take no part,
    nor do rows with a null id; all others must have one length, else this
    raises, as an inner product isn't defined. A repeated
    query id is answered once, from its first vector by order; a repeated
    candidate is listed as often as it comes, but never for its own id.
    """
    used = vectors.filter(F.col(id_col).isNotNull() & usable(vector_col)).select(F.col(id_col).cast("long").alias("i"), quantised(vector_col, scale).alias("x"), is_query.alias("q"))
    rows = cut(used, "vectors")
    lengths = rows.agg(F.min(F.size("x")).alias("lo"), F.max(F.size("x")).alias("hi")).first()
    if lengths["lo"] != lengths["hi"]:
        raise ValueError(f"vectors of {lengths['lo']} to {lengths['hi']} components have no inner products")
    queries = rows.filter("q").groupBy("i").agg(F.min("x").alias("x"))
    total = queries.count()
    blocks = max(1, math.ceil(total / block))
    queries = cut(queries.withColumn("b", F.pmod(F.xxhash64("i"), F.lit(blocks)).cast("int")), "queries")
    context, parts = vectors.sparkSession.sparkContext, []
    for b in range(blocks if total else 0):
        held = queries.filter(F.col("b") == b).select("i", "x").toArrow()
        ids = held.column("i").to_numpy()
        order = np.argsort(ids)
        sent = context.broadcast((ids[order], np.stack(held.column("x").to_numpy()).astype(np.float64)[order]))

        def run(batches, sent=sent):
            search = Searcher(*sent.value, k, resolutions)
            for batch in batches:
                for a in range(0, batch.num_rows, TILE_ROWS):
                    part = batch.slice(a, TILE_ROWS)
                    flat = part.column("x").flatten().to_numpy()
                    search.show(part.column("i").to_numpy(), flat.reshape(part.num_rows, -1))
            q, at = np.nonzero(np.isfinite(search.score))
            yield pa.RecordBatch.from_arrays([pa.array(search.ids[q]), pa.array(search.best[q, at]), pa.array(search.score[q, at].astype(np.int64))], names=["query_id", "vec_id", "score"])

        found = rows.select("i", "x").mapInArrow(tidy(run), "query_id long, vec_id long, score long")
        parts.append(cut(_first(found, k), f"block-{b}") if blocks > 1 else _first(found, k))
    if not parts:
        return vectors.sparkSession.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    out = parts[0]
    for more in parts[1:]:
        out = out.unionByName(more)
    return out


def _first(found: DataFrame, k: int) -> DataFrame:
    """The k first of each query of what the tasks have kept: k rows a task and query at most."""
    from pyspark.sql import Window

    by = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(by)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
