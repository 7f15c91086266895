"""Approximate nearest neighbours by collision counting.

Each of ``lines`` random projections of the unit vectors is one sorted array. A query opens a window around its own
projection on every line; a vector collides where it falls into the window. Windows widen step by step (virtual
rehashing: nothing is hashed again, only the rims are read). A vector with ``share`` of all lines as
collisions is verified: its cosine with the query is computed in double precision on the original vectors.
The search of a query ends when a vector nearer than its k-th best would, with ``sure`` standard deviations to spare,
have passed the threshold already, when ``enough`` of all vectors are verified, or when all are.

Every row is indexed: rows are dealt to chunks of about ``chunk`` by a hash of their id, a task builds the arrays of a
chunk, and the best k over chunks are the result, whatever the layout of files. Queries are taken in blocks of at most
``block``; a block is broadcast, meets all chunks, and is given up before the next one.

Defined results: vectors that are null, zero, or hold null or non-finite components take no part, as query or
candidate; vectors of different lengths are never compared; equal cosines rank by smaller id; a query id that repeats is
asked once, with its least vector, and rows that share its id are not its candidates; fewer candidates give fewer
rows; an empty table gives none; columns other than id and vector are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vpcoreset.llm.common import groups, stored, trimmed

#: Projections of unit vectors are normal numbers; none comes near half of this, and windows stop at it.
GAP = 1_000.0
#: Vectors that a search verifies in any chunk before it may stop by their number.
LEAST = 400


def _lines(dim: int, n: int, seed: int) -> np.ndarray:
    return np.random.default_rng([seed, dim]).standard_normal((dim, n)).astype(np.float32)


class CollisionIndex:
    """Sorted projections of a chunk of vectors of one length."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, lines: int, seed: int, share: float = 0.6, sure: float = 1.5, start: float = 0.5, step: float = 0.06, enough: float = 0.08):
        self.ids, self.vectors = ids, vectors.astype(np.float64)
        self.norms = np.sqrt((self.vectors * self.vectors).sum(1))
        self.axes = _lines(vectors.shape[1], lines, seed)
        place = (self.vectors / self.norms[:, None]).astype(np.float32) @ self.axes
        self.order = np.ascontiguousarray(np.argsort(place, axis=0, kind="stable").T)
        # All lines in one array: line j is shifted by j * GAP, more than any width of a window.
        self.shift = np.arange(lines) * GAP
        self.place = (np.take_along_axis(place.T, self.order, 1) + self.shift[:, None]).ravel()
        self.order = self.order.ravel()
        self.first = np.arange(lines) * len(ids)
        self.lines, self.share, self.sure, self.start, self.step, self.enough = lines, share, sure, start, step, enough

    def cosines(self, at: np.ndarray, query: np.ndarray) -> np.ndarray:
        return (self.vectors[at] * query).sum(1) / (self.norms[at] * math.sqrt((query * query).sum()))

    def _passed(self, half: float, distance: float) -> bool:
        """Whether a vector at this distance has surely collided often enough."""
        p = math.erf(half / max(distance, 1e-9) / math.sqrt(2))
        return self.lines * p - self.sure * math.sqrt(self.lines * p * (1 - p)) >= self.share * self.lines

    def search(self, query_id: int, query: np.ndarray, k: int) -> tuple[list[tuple[float, int]], int]:
        """Best k as (cosine, id), and how many vectors were verified."""
        n, need = len(self.ids), math.ceil(self.share * self.lines)
        centre = (query / math.sqrt((query * query).sum())).astype(np.float32) @ self.axes + self.shift
        low = np.minimum(np.maximum(np.searchsorted(self.place, centre), self.first), self.first + n)
        high, hits = low.copy(), np.zeros(n, np.int64)
        verified = np.zeros(n, bool)
        verified[self.ids == query_id] = True
        best: list[tuple[float, int]] = []
        half, done = 0.0, 0
        while True:
            half += self.step if half else self.start
            new_low = np.minimum(np.maximum(np.searchsorted(self.place, centre - half, "left"), self.first), low)
            new_high = np.maximum(np.minimum(np.searchsorted(self.place, centre + half, "right"), self.first + n), high)
            rims = [self.order[a:b] for a, b in zip(new_low.tolist(), low.tolist(), strict=True) if b > a] + [self.order[a:b] for a, b in zip(high.tolist(), new_high.tolist(), strict=True) if b > a]
            if rims:
                hits += np.bincount(np.concatenate(rims), minlength=n)
            low, high = new_low, new_high
            at = np.flatnonzero((hits >= need) & ~verified)
            if len(at):
                verified[at] = True
                done += len(at)
                score = self.cosines(at, query)
                best = sorted([*best, *zip((-score).tolist(), self.ids[at].tolist(), strict=True)])[:k]
            if verified.all() or (len(best) == k and (done >= k + max(self.enough * n, LEAST) or self._passed(half, math.sqrt(max(0.0, 2 + 2 * best[-1][0]))))):
                return [(-s, i) for s, i in best], done


def nearest(rows: DataFrame, *, id_col: str = "vec_id", vector_col: str = "embedding", k: int = 5, every: int = 50, lines: int = 128, chunk: int = 16_384, block: int = 2_048, seed: int = 11) -> DataFrame:
    """(query_id, rank, id, score): the k nearest found of each query, an id divisible by ``every``."""
    v = F.col(vector_col)
    ok = v.isNotNull() & (F.size(v) > 0) & F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(v, lambda x: x != 0)
    rows = rows.where(F.coalesce(ok, F.lit(False)) & F.col(id_col).isNotNull()).select(F.col(id_col).alias("id"), v.cast("array<double>").alias("v"))
    rows = stored(rows, "vectors")
    chunks = -(-rows.count() // chunk) or 1
    # Chunks by hash of the id: what a query finds does not depend on files, partitions or batches.
    dealt = rows.withColumn("chunk", F.pmod(F.xxhash64("id"), F.lit(chunks)).cast("int"))
    dealt = dealt.repartition(min(chunks, 65_536), "chunk").sortWithinPartitions("chunk", "id")
    queries = rows.where(F.pmod(F.col("id"), F.lit(every)) == 0)
    blocks = -(-queries.count() // block) or 1
    out = None
    for b in range(blocks):
        part = queries if blocks == 1 else queries.where(F.pmod(F.xxhash64("id"), F.lit(blocks)) == b)
        asked = sorted((r["id"], r["v"]) for r in part.groupBy("id").agg(F.min("v").alias("v")).collect())
        held = rows.sparkSession.sparkContext.broadcast([(i, np.array(x)) for i, x in asked])

        def search(batches: Iterator[pd.DataFrame], held=held) -> Iterator[pd.DataFrame]:
            for own in groups(batches, ["chunk"]):
                for dim, same in own.groupby(own["v"].map(len)):
                    index = CollisionIndex(same["id"].to_numpy(), np.stack(same["v"].to_list()), lines, seed)
                    found = [(q, i, s) for q, x in held.value if len(x) == dim for s, i in index.search(q, x, k)[0]]
                    if found:
                        yield pd.DataFrame(found, columns=["query_id", "id", "score"])

        found = dealt.mapInPandas(trimmed(search), "query_id long, id long, score double")
        if blocks > 1:  # one block of queries at a time: its finds are written, its broadcast is given up
            best = F.row_number().over(W.partitionBy("query_id").orderBy(F.desc("score"), "id"))
            found = stored(found.withColumn("rank", best).where(F.col("rank") <= k).drop("rank"), "found")
            held.destroy()
        out = found if out is None else out.unionByName(found)
    best = F.row_number().over(W.partitionBy("query_id").orderBy(F.desc("score"), "id"))
    return out.withColumn("rank", best).where(F.col("rank") <= k).select("query_id", "rank", F.col("id").alias(id_col), "score")
