"""Approximate nearest neighbours with a hash-prefix forest.

A tree is a sorted array of 64-bit hash strings, one bit for the side of each of 64 random planes. A
query first descends every tree to the longest prefix that any entry shares with it, which is a range
of the sorted array; then all trees ascend together, one bit a step, and the ranges widen, until they
hold `wanted` entries. Those candidates, and no others, are compared exactly by cosine in double
precision.

The index is cut into blocks of bounded size by a hash of the id, and queries into batches; a task
answers one batch against one block's forest, and the best of all blocks are merged. Exactly equal
vectors of a block are one entry with its smallest ids, as many as an answer can need, so a vector with
a third of all rows costs no more than another one.

Planes are drawn from a fixed seed, so nothing is fitted to the data. Defined results: vectors that are
null, empty, zero or hold a null, NaN or infinite component take no part, nor do null ids or vectors
of another length than the query; ties go to the smaller id; repeated rows of one id and one vector
count once; an empty table gives no rows.
"""

from __future__ import annotations

import functools

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from galoislake.llm.common import settle, table
from galoislake.llm.vectors import matrix, unit, usable

TREES = 48
BITS = 64
SHARE = 1.2  # entries wanted from the trees, as a multiple of the block's rows; an entry in many trees counts in each
LEAST = 256
BLOCK, BATCH = 8192, 2048


@functools.cache
def planes(size: int, trees: int = TREES) -> np.ndarray:
    return np.random.default_rng(20_240_229).standard_normal((trees, size, BITS))


def hash_strings(u: np.ndarray, trees: int) -> np.ndarray:
    """One row of keys for each tree."""
    out = np.empty((trees, len(u)), dtype=np.uint64)
    for t, h in enumerate(planes(u.shape[1], trees)):
        out[t] = np.packbits(u @ h > 0, axis=1).view(">u8").ravel()
    return out


class Forest:
    def __init__(self, u: np.ndarray, trees: int = TREES):
        self.u, self.trees = u, trees
        keys = hash_strings(u, trees)
        self.order = keys.argsort(axis=1, kind="stable")
        self.keys = np.take_along_axis(keys, self.order, axis=1)

    def candidates(self, q: np.ndarray, wanted: int) -> list[np.ndarray]:
        """Entries that the trees hold for each query when together they first hold `wanted`. On the
        last step of a query its trees ascend in turn, and no more of them than are needed."""
        n, keys = len(q), hash_strings(q, self.trees)
        low, high = np.zeros((self.trees, n), dtype=np.int64), np.zeros((self.trees, n), dtype=np.int64)
        rising = np.arange(n)
        for depth in range(BITS, -1, -1):
            lo, hi = self._ranges(keys[:, rising], depth)
            gain = (hi - lo) - (high - low)[:, rising]
            held = (high - low)[:, rising].sum(axis=0) + gain.cumsum(axis=0)
            up = held - gain < wanted
            low[:, rising], high[:, rising] = np.where(up, lo, low[:, rising]), np.where(up, hi, high[:, rising])
            rising = rising[held[-1] < wanted]
            if not len(rising):
                break
        out, seen = [], np.zeros(len(self.u), dtype=bool)
        for i in range(n):
            for t in range(self.trees):
                seen[self.order[t, low[t, i] : high[t, i]]] = True
            out.append(np.flatnonzero(seen))
            seen[:] = False
        return out

    def _ranges(self, keys: np.ndarray, depth: int) -> tuple[np.ndarray, np.ndarray]:
        """The range of each tree whose entries share the first `depth` bits of a key."""
        if not depth:
            return np.zeros(keys.shape, dtype=np.int64), np.full(keys.shape, len(self.u), dtype=np.int64)
        shift = np.uint64(BITS - depth)
        first = keys >> shift << shift
        last = first | np.uint64((1 << (BITS - depth)) - 1)
        return tuple(np.stack([np.searchsorted(k, f, side) for k, f in zip(self.keys, x, strict=True)]) for x, side in ((first, "left"), (last, "right")))


def search(vectors: DataFrame, queries: DataFrame, k: int = 5, trees: int = TREES, share: float = SHARE, block: int = BLOCK, batch: int = BATCH, *, vec_id: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id and score of the k nearest found of every query, itself left out."""
    fit = lambda df: df.where(F.col(vec_id).isNotNull() & usable(F.col(vector))).select(F.col(vec_id).cast("long").alias("id"), F.col(vector).cast("array<double>").alias("x"), F.size(vector).alias("size"))
    index, asked = fit(vectors), settle(fit(queries).distinct(), "queries")
    blocks, batches = max(1, -(-index.count() // block)), max(1, -(-asked.count() // batch))
    salt = F.xxhash64("id")
    rows = index.select("id", "x", "size", F.lit(False).alias("asks"), F.pmod(salt, F.lit(blocks)).alias("block"), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(batches - 1).cast("long"))).alias("batch"))
    asks = asked.select("id", "x", "size", F.lit(True).alias("asks"), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long"))).alias("block"), F.pmod(salt, F.lit(batches)).alias("batch"))

    def answer(t: pa.Table) -> pa.Table:
        query, near, score = _answers(t, k, trees, share)
        return pa.table({"query_id": pa.array(query, pa.int64()), "vec_id": pa.array(near, pa.int64()), "score": pa.array(score, pa.float64())})

    found = rows.unionByName(asks).groupBy("block", "batch", "size").applyInArrow(answer, "query_id long, vec_id long, score double")
    best = found.groupBy("query_id").agg(F.slice(F.array_sort(F.collect_set(F.struct((-F.col("score")).alias("s"), "vec_id"))), 1, k).alias("best"))  # k of each block
    return best.select("query_id", F.posexplode("best").alias("at", "b")).select("query_id", (F.col("at") + 1).alias("rank"), F.col("b.vec_id").alias("vec_id"), (-F.col("b.s")).alias("score"))


def _answers(t: pa.Table, k: int, trees: int, share: float) -> tuple[list[int], list[int], list[float]]:
    asks = t.column("asks").to_numpy()
    ids, x = t.column("id").to_numpy(), matrix(t.column("x"))
    query, near, score = [], [], []
    if asks.all() or not asks.any():
        return query, near, score
    own, q = np.flatnonzero(~asks), np.flatnonzero(asks)
    own = own[ids[own].argsort(kind="stable")]
    raw = np.ascontiguousarray(x[own])
    _, first, group = np.unique(raw.view(f"V{raw.shape[1] * 8}").ravel(), return_index=True, return_inverse=True)
    by = np.argsort(group, kind="stable")
    cut = np.searchsorted(group[by], np.arange(len(first) + 1))
    members = [np.unique(ids[own[by[a:b]]])[: k + 1] for a, b in zip(cut[:-1], cut[1:], strict=True)]  # k and the query itself
    y = raw[first]
    norm = np.linalg.norm(y, axis=1)
    forest = Forest(y / norm[:, None], trees)
    wanted = max(LEAST, int(share * len(y)))
    for i, some in zip(q, forest.candidates(unit(x[q]), wanted), strict=True):
        cos = y[some] @ x[i] / (norm[some] * np.linalg.norm(x[i]))
        if len(some) > 4 * k:
            best = cos >= np.partition(cos, -k - 1)[-k - 1]
            some, cos = some[best], cos[best]
        pairs = sorted((-c, int(m)) for c, e in zip(cos.tolist(), some, strict=True) for m in members[e] if m != ids[i])[:k]
        query += [int(ids[i])] * len(pairs)
        near += [m for _, m in pairs]
        score += [-c for c, _ in pairs]
    return query, near, score


def op3_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "embeddings")
    return search(rows, rows.where("vec_id % 50 = 0"))
