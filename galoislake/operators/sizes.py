"""How many intents of each size a context has, without keeping the intents.

The family is cut into subtrees: what lies below an intent and adds no attribute up to the last one added. A
task goes through its subtrees in batches of intents. Where an intent has many rows, these are dealt out over the
attributes to add; once at most `FEW` rows are left that have more than the intent, a set of them is the bits of a
number, and what they share is looked up byte by byte. Nothing is left out, and batches are bounded.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from galoislake.functions import bits
from galoislake.operators.central import MOST_ROWS, local
from galoislake.operators.context import FormalContext

MOST = 1 << 15  # intents that a task takes up at once
FEW = 64  # rows as the bits of a number
_AT_ONCE = 1 << 17  # rows of a batch

Node = tuple[np.ndarray, int, int]  # the rows that have the intent, the intent, the rank of the last attribute added


def _rare_first(rows: np.ndarray, m: int) -> np.ndarray:
    """The rows with the attributes in the order of their supports, which leaves fewer sets to other subtrees;
    sizes do not depend on the order."""
    has = [rows >> bits.WORD - 1 - r & 1 for r in range(m)]
    out = np.zeros_like(rows)
    for place, r in enumerate(sorted(range(m), key=lambda r: int(has[r].sum()))):
        out |= has[r] << bits.WORD - 1 - place
    return out


@dataclass
class _Batch:
    """Intents in the order of the last attribute added; rows: those that have more attributes after it than the
    intent, those of one intent behind those of the one before."""

    intents: np.ndarray
    last: np.ndarray
    rows: np.ndarray
    lengths: np.ndarray

    def where(self, kept: np.ndarray) -> _Batch:
        return _Batch(self.intents[kept], self.last[kept], self.rows[np.repeat(kept, self.lengths)], self.lengths[kept])

    def bounded(self, most: int) -> tuple[_Batch, _Batch | None]:
        """The first intents that are handled at once, and the rest."""
        ends = np.cumsum(self.lengths)
        high = max(1, min(most, int(np.searchsorted(ends, _AT_ONCE, "right"))))
        if high >= len(self.intents):
            return self, None
        at = int(ends[high - 1])
        return tuple(_Batch(self.intents[s], self.last[s], self.rows[r], self.lengths[s]) for s, r in ((slice(high), slice(at)), (slice(high, None), slice(at, None))))


def _batch(nodes: list[Node]) -> _Batch:
    nodes = sorted(nodes, key=lambda node: node[2])
    some = [rows[rows & ~intent & (1 << bits.WORD - 1 - last) - 1 != 0] for rows, intent, last in nodes]
    return _Batch(np.array([n[1] for n in nodes], np.int64), np.array([n[2] for n in nodes], np.int64), np.concatenate(some), np.array([len(x) for x in some]))


def _below(b: _Batch, m: int) -> _Batch:
    """The intents right below those of the batch, each once: an attribute beyond the last one is added and closed,
    and the closure is kept if it adds nothing before that attribute."""
    owner = np.repeat(np.arange(len(b.intents)), b.lengths)
    more, ends = b.rows & ~b.intents[owner], np.cumsum(b.lengths)
    found = [_Batch(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64))]
    for p in range(int(b.last[0]) + 1, m):
        own = 1 << bits.WORD - 1 - p
        asked = int(ends[np.searchsorted(b.last, p) - 1])
        at = np.flatnonzero(more[:asked] & own)
        if not len(at):
            continue
        rows, parent = b.rows[at], owner[at]
        starts = np.flatnonzero(np.concatenate([[True], parent[1:] != parent[:-1]]))
        closed = np.bitwise_and.reduceat(rows, starts)
        kept = (closed & ~b.intents[parent[starts]]) >> bits.WORD - p == 0
        child = np.repeat(np.arange(len(starts)), np.diff(np.append(starts, len(at))))
        on = kept[child] & (rows & ~closed[child] & own - 1 != 0)
        found.append(_Batch(closed[kept], np.full(int(kept.sum()), p), rows[on], np.bincount(child[on], minlength=len(starts))[kept]))
    return _Batch(*[np.concatenate([getattr(x, f) for x in found]) for f in ("intents", "last", "rows", "lengths")])


def _transposed(x: np.ndarray) -> np.ndarray:
    """64 words of 64 bits in each column of x: bit i of word k becomes bit k of word i, in place."""
    j, mask = 32, np.uint64(0xFFFFFFFF)
    while j:
        y = x.reshape(32 // j, 2, j, -1)
        low, high = y[:, 0], y[:, 1]
        moved = (low >> np.uint64(j) ^ high) & mask
        high ^= moved
        low ^= moved << np.uint64(j)
        j >>= 1
        mask ^= mask << np.uint64(j)
    return x


def _tables(rows: np.ndarray) -> np.ndarray:
    """rows[k] is the k-th row of each base, -1 for none. For each base, and each eight of its rows, what the rows
    of every byte share."""
    eights, bases = len(rows) // 8, rows.shape[1]
    out, own = np.full((bases, eights, 256), -1, np.int64), rows.T.reshape(bases, eights, 8)
    for j in range(8):
        np.bitwise_and(out[:, :, : 1 << j], own[:, :, j : j + 1], out=out[:, :, 1 << j : 2 << j])
    return out.reshape(-1)


class _Tally:
    """sizes: how many intents of each size, 0 to m, of the subtrees taken up so far."""

    def __init__(self, m: int, most: int):
        self.m, self.most, self.sizes = m, most, np.zeros(m + 1, np.int64)
        self.few: dict[int, list[tuple[np.ndarray, np.ndarray, np.ndarray]]] = {}  # by eights of rows

    def _count(self, intents: np.ndarray) -> None:
        self.sizes += np.bincount(np.bitwise_count(intents), minlength=self.m + 1)

    def add(self, b: _Batch) -> None:
        stack = self._sorted_out(b)
        while stack:
            b, rest = stack.pop().bounded(self.most)
            if rest is not None:
                stack.append(rest)
            stack += self._sorted_out(_below(b, self.m))

    def _sorted_out(self, b: _Batch) -> list[_Batch]:
        """Counts the intents, keeps those of few rows for later, and gives those of many back."""
        self._count(b.intents)
        at, eights = np.cumsum(b.lengths) - b.lengths, -(-b.lengths // 8)
        for k in np.unique(eights[(b.lengths > 0) & (b.lengths <= FEW)]).tolist():
            some, place = np.flatnonzero(eights == k), np.arange(8 * k)[:, None]
            rows = np.where(place < b.lengths[some], b.rows[np.minimum(at[some] + place, len(b.rows) - 1)], -1)
            self.few.setdefault(k, []).append((rows, b.intents[some], b.last[some]))
            if sum(len(x[1]) for x in self.few[k]) >= self._bases():
                self._settle(k)
        many = b.lengths > FEW
        return [b.where(many)] if many.any() else []

    def _bases(self) -> int:
        return max(1, self.most >> 7)

    def _settle(self, k: int) -> None:
        rows, intents, last = (np.concatenate(x, axis=-1) for x in zip(*self.few.pop(k), strict=True))
        for i in range(0, len(last), self._bases()):
            s = slice(i, i + self._bases())
            self._few_rows(rows[:, s], intents[s], last[s])

    def done(self) -> np.ndarray:
        for k in list(self.few):
            self._settle(k)
        return self.sizes

    def _few_rows(self, rows: np.ndarray, intents: np.ndarray, last: np.ndarray) -> None:
        """The subtrees of bases of few rows: an extent is a number, bit k for the k-th row of its base."""
        m, shared, words, present = self.m, _tables(rows), 256 * (len(rows) // 8), rows >= 0
        has = np.zeros((64, rows.shape[1]), np.uint64)
        has[: len(rows)] = np.where(present, rows, 0).view(np.uint64)
        has = _transposed(has)[bits.WORD - 1 :: -1]  # for each rank, the rows of each base that have it
        one = np.uint64(1)
        every = np.bitwise_or.reduce(np.where(present, one << np.arange(len(rows), dtype=np.uint64)[:, None], np.uint64(0)), axis=0)
        order = np.argsort(last, kind="stable")
        stack = [(every[order], intents[order], order, last[order])]
        while stack:
            at = stack.pop()
            if len(at[0]) > self.most:
                stack.append(tuple(x[self.most :] for x in at))
                at = tuple(x[: self.most] for x in at)
            extent, intent, base, last = at
            lacks, first = ~intent, int(last[0]) + 1
            grown, parents = [extent[:0]], [base[:0]]
            for p in range(first, m):
                n = int(np.searchsorted(last, p))
                met = extent[:n] & has[p][base[:n]]
                asked = np.flatnonzero((met != 0) & (lacks[:n] & 1 << bits.WORD - 1 - p != 0))
                grown.append(met[asked])
                parents.append(asked)
            added = np.repeat(np.arange(first - 1, m)[: len(grown)], [len(x) for x in grown])
            extent, parent = np.concatenate(grown), np.concatenate(parents)
            base = base[parent]
            octets, place = extent.astype("<u8").view(np.uint8).reshape(-1, 8), base * words
            closed = shared[place + octets[:, 0]]
            for k in range(1, len(rows) // 8):
                place += 256
                closed &= shared[place + octets[:, k]]
            kept = np.flatnonzero((closed & lacks[parent]) >> bits.WORD - added == 0)
            self._count(closed[kept])
            kept = kept[extent[kept] & extent[kept] - one != 0]  # a single row closes to itself: nothing lies below
            if len(kept):
                stack.append((extent[kept], closed[kept], base[kept], added[kept]))


def subtree_sizes(node: Node, m: int, most: int = MOST) -> np.ndarray:
    """How many intents of each size, 0 to m, the node's subtree has."""
    tally = _Tally(m, most)
    tally.add(_batch([node]))
    return tally.done()


def _rooted(batches: Iterator[pa.RecordBatch], every: np.ndarray) -> Iterator[_Batch]:
    """Subtrees given by intent and last, with their rows, a bounded number at once."""
    for b in batches:
        nodes, held = [], 0
        for intent, last in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
            nodes.append((every[every & intent == intent], intent, last))
            held += len(nodes[-1][0])
            if held >= _AT_ONCE:
                yield _batch(nodes)
                nodes, held = [], 0
        if nodes:
            yield _batch(nodes)


def counts_by_size(ctx: FormalContext, most_rows: int = MOST_ROWS, most: int = MOST) -> DataFrame:
    """size and concepts, for contexts of one word. The rows, of a checked number, go to every task."""
    if len(ctx.words) != 1:
        raise ValueError(f"more than {bits.WORD} attributes: mine the family")
    m, spark, rows = ctx.m, ctx.spark, _rare_first(local(ctx, most_rows).words[:, 0], ctx.m)
    top, roots = _Tally(m, most), []
    if not (rows == ctx.full[0]).any():
        top.sizes[m] += 1  # the set of all attributes, which no row has
    if len(rows):
        first = _batch([(rows, int(np.bitwise_and.reduce(rows)), -1)])
        rest = _below(first, m)
        top._count(first.intents)
        top._count(rest.intents)
        while rest is not None and len(rest.intents):
            some, rest = rest.bounded(most)
            below = _below(some, m)
            roots += zip(below.intents.tolist(), below.last.tolist(), strict=True)
    held = spark.sparkContext.broadcast(rows)

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """The subtrees themselves, without what lies below, and those right below."""
        for b in _rooted(batches, held.value):
            below = _below(b, m)
            yield pa.RecordBatch.from_arrays([pa.array(b.intents), pa.array(np.full(len(b.intents), m - 1, np.int32))], names=["intent", "last"])
            yield pa.RecordBatch.from_arrays([pa.array(below.intents), pa.array(below.last.astype(np.int32))], names=["intent", "last"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tally = _Tally(m, most)
        for b in _rooted(batches, held.value):
            tally.add(b)
        yield pa.RecordBatch.from_arrays([pa.array(range(m + 1), pa.int32()), pa.array(tally.done())], names=["size", "concepts"])

    known = spark.createDataFrame([(k, int(n)) for k, n in enumerate(top.sizes)], "size int, concepts long")
    cuts = spark.createDataFrame(roots, "intent long, last int")
    tasks = max(1, min(len(roots) // 8, 16 * spark.sparkContext.defaultParallelism))
    cuts = cuts.repartition(tasks).mapInArrow(cut, "intent long, last int")
    found = cuts.repartition(tasks).mapInArrow(run, "size int, concepts long")
    return known.unionByName(found).groupBy("size").agg(F.sum("concepts").alias("concepts")).where("concepts > 0")
