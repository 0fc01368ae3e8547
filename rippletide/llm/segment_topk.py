"""Exact top-k by inner product with multi-resolution segment statistics.

Components become integers floor(scale * x). For several segment counts (coarse to fine) a vector
keeps each segment's mean and deviation. Within a segment of m components,
<q, v> <= m * (mean_q * mean_v + dev_q * dev_v), which is the same as a lower bound on the squared
distance given the norms; summed over segments it bounds the score. A candidate is tested against a
query's k-th best score so far, at each resolution in turn, and only survivors get an exact product.

Queries go in blocks of at most ``block`` vectors; a block is what a scan of all rows carries, so its
size is fixed whatever the data. Each task keeps k rows a query; a window per query merges them.

Defined results: vectors that are null, or hold a null or a non-finite component, take no part;
vectors of different lengths do not meet; rows that repeat an id are candidates each; a repeated query id
is asked once, by its smallest vector, and of its own rows only that one is left out.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

LEVELS = (1, 4, 16)


def _segments(x: np.ndarray, parts: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sizes, means and population deviations of ``parts`` near-equal segments of each row."""
    cuts = np.linspace(0, x.shape[1], min(parts, x.shape[1]) + 1).astype(int)
    sizes = np.diff(cuts).astype(float)
    means = np.add.reduceat(x, cuts[:-1], axis=1) / sizes
    spread = x - np.repeat(means, np.diff(cuts), axis=1)
    return sizes, means, np.sqrt(np.add.reduceat(spread * spread, cuts[:-1], axis=1) / sizes)


def features(x: np.ndarray, parts: int, scaled: bool) -> np.ndarray:
    """Row features whose product between a scaled and an unscaled side is the bound."""
    sizes, means, devs = _segments(x, parts)
    both = np.concatenate([means, devs], axis=1)
    return both * np.concatenate([sizes, sizes]) if scaled else both


class BlockSearch:
    """Running top-k of a block of queries (one vector length) over batches of candidates."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, k: int) -> None:
        # One more than asked for: the query's own row is among the candidates and goes at the end.
        self.ids, self.x, self.k = ids, vectors.astype(float), k + 1
        self.sides = [features(self.x, p, True) for p in LEVELS]
        self.top: list[list[tuple[int, int]]] = [[] for _ in ids]
        self.bar = np.full(len(ids), -np.inf)
        self.exact = self.tested = 0

    def _scores(self, q: int, v: np.ndarray) -> np.ndarray:
        if np.abs(self.x[q]).max(initial=0) * np.abs(v).max(initial=0) * max(v.shape[1], 1) < 2**52:
            return (v @ self.x[q]).astype(np.int64)
        return np.array([sum(int(a) * int(b) for a, b in zip(self.x[q], row, strict=True)) for row in v], object)

    def add(self, ids: np.ndarray, vectors: np.ndarray) -> None:
        v = vectors.astype(float)
        if v.shape[1] == 0:
            bounds = [np.zeros((len(self.ids), len(v)))]
            sides = []
        else:
            sides = [features(v, p, False) for p in LEVELS]
            bounds = [self.sides[0] @ sides[0].T]
        for q in range(len(self.ids)):
            slack = 1e-6 * (1 + abs(self.bar[q])) if np.isfinite(self.bar[q]) else 0.0
            alive = np.flatnonzero(bounds[0][q] >= self.bar[q] - slack)
            for level in range(1, len(sides)):
                if len(alive) and np.isfinite(self.bar[q]):
                    alive = alive[sides[level][alive] @ self.sides[level][q] >= self.bar[q] - slack]
            self.tested += len(v)
            self.exact += len(alive)
            if not len(alive):
                continue
            scores = self._scores(q, v[alive])
            if len(alive) > 4 * self.k and scores.dtype != object:  # only rows that can still be among the best
                best = np.lexsort((ids[alive], -scores))[: self.k]
                alive, scores = alive[best], scores[best]
            self.top[q] = sorted(self.top[q] + [(-s, i) for s, i in zip(scores.tolist(), ids[alive].tolist(), strict=True)])[: self.k]
            if len(self.top[q]) == self.k:
                self.bar[q] = -self.top[q][-1][0]


def _search(batches: Iterator[pa.RecordBatch], block: dict[int, tuple[np.ndarray, np.ndarray]], k: int) -> Iterator[pa.RecordBatch]:
    searches = {d: BlockSearch(ids, x, k) for d, (ids, x) in block.items()}
    for batch in batches:
        ids = batch.column(0).to_numpy()
        lists = batch.column(1)
        sizes = np.diff(np.asarray(lists.offsets))
        flat = lists.flatten().to_numpy()
        starts = np.concatenate([[0], np.cumsum(sizes)[:-1]]) if len(sizes) else np.zeros(0, int)
        for d in np.unique(sizes):
            if int(d) in searches:
                rows = np.flatnonzero(sizes == d)
                for i in range(0, len(rows), 4096):
                    some = rows[i : i + 4096]
                    searches[int(d)].add(ids[some], flat[starts[some][:, None] + np.arange(d)])
    out = []
    for s in searches.values():
        for q, found in enumerate(s.top):
            own = int(s._scores(q, s.x[q : q + 1])[0]) if found else 0
            out += [(int(s.ids[q]), i, -v, i == s.ids[q] and -v == own) for v, i in found]
    yield pa.RecordBatch.from_arrays([*[pa.array([r[c] for r in out], pa.int64()) for c in range(3)], pa.array([bool(r[3]) for r in out], pa.bool_())], names=["query_id", "vec_id", "score", "own"])


def quantised(column: Column, scale: int = 256) -> Column:
    return F.transform(column.cast("array<double>"), lambda x: F.floor(x * scale))


def usable(column: Column) -> Column:
    finite = lambda x: F.coalesce(~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))), F.lit(False))
    return column.isNotNull() & F.forall(column.cast("array<double>"), finite)


def top_k(vectors: DataFrame, is_query: Column, k: int = 5, scale: int = 256, block: int = 4096, key: str = "vec_id", column: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score: the k best rows for every query row."""
    spark = vectors.sparkSession
    rows = vectors.where(F.col(key).isNotNull() & usable(F.col(column))).select(F.col(key).cast("long").alias("vec_id"), quantised(F.col(column), scale).alias("v"), F.coalesce(is_query, F.lit(False)).alias("q"))
    asked = rows.where("q").groupBy("vec_id").agg(F.min("v").alias("v"))
    n = asked.count()
    found = None
    blocks = -(-n // block)
    for b in range(blocks):
        held: dict[int, tuple[list, list]] = {}
        # Expected size n / blocks <= block: a hash deals the queries out evenly.
        for r in asked.where(F.pmod(F.xxhash64("vec_id"), F.lit(blocks)) == b).toLocalIterator():
            ids, xs = held.setdefault(len(r["v"]), ([], []))
            ids.append(r["vec_id"])
            xs.append(r["v"])
        part = {d: (np.array(ids, np.int64), np.array(xs, np.int64).reshape(len(ids), d)) for d, (ids, xs) in held.items()}
        one = rows.select("vec_id", "v").mapInArrow(lambda it, part=part: _search(it, part, k), "query_id long, vec_id long, score long, own boolean")
        found = one if found is None else found.union(one)
    if found is None:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    # One of the rows that are like the query itself is the query.
    mine = Window.partitionBy("query_id", "own").orderBy("score")
    best = found.where("own").withColumn("n", F.row_number().over(mine)).where("n > 1").drop("n").union(found.where("not own"))
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return best.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
