"""The centralized baselines, and subtrees finished inside of tasks.

Both baselines run on the driver over the distinct rows of a context, whose size is checked first; they
are cross-checks and yardsticks, not the way for large contexts. Rows are Python integers of m bits, the
lowest rank highest, so lectic order is numeric order.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from itertools import islice

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from galoislake.functions import bits
from galoislake.operators.context import FormalContext
from galoislake.operators.extents import Rows
from galoislake.plans.storage import new_path

MOST_ROWS = 1_000_000
AT_ONCE = 500_000  # intents that the driver holds at once

Found = tuple[np.ndarray, np.ndarray, np.ndarray]  # packed intents, supports, numbers


class LocalContext:
    """Distinct rows as bit columns: for each attribute, the set of rows that have it, as one integer."""

    def __init__(self, words: np.ndarray, weights: np.ndarray, m: int):
        self.m, self.n, self.words, self.weights = m, len(words), words, np.asarray(weights, dtype=np.int64)
        self.all_rows = (1 << self.n) - 1
        self.columns = []
        for r in range(m):
            has = (words[:, r // bits.WORD] >> (bits.WORD - 1 - r % bits.WORD) & 1).astype(np.uint8)
            self.columns.append(int.from_bytes(np.packbits(has, bitorder="little").tobytes(), "little") if self.n else 0)
        self.closures = 0

    def rows(self) -> Rows:
        return Rows(self.words, self.weights, self.m)

    def extent(self, attributes: Sequence[int]) -> int:
        out = self.all_rows
        for a in attributes:
            out &= self.columns[a]
        return out

    def intent(self, extent: int) -> frozenset[int]:
        self.closures += 1
        return frozenset(a for a in range(self.m) if extent & self.columns[a] == extent)

    def support(self, extent: int) -> int:
        on = np.unpackbits(np.frombuffer(extent.to_bytes(-(-self.n // 8) or 1, "little"), np.uint8), bitorder="little")[: self.n]
        return int(self.weights @ on)


def local(ctx: FormalContext, most: int = MOST_ROWS) -> LocalContext:
    rows = ctx.rows.select(*ctx.words, "weight").limit(most + 1).toArrow()
    if rows.num_rows > most:
        raise ValueError(f"more than {most} distinct rows: use the distributed methods")
    return LocalContext(np.stack([rows.column(w).to_numpy() for w in ctx.words], axis=1), rows.column("weight").to_numpy(), ctx.m)


def successor(at: LocalContext, d: frozenset[int]) -> tuple[frozenset[int], int] | None:
    """(next intent in lectic order, its extent), or None after the last one.

    Prefix extents are shared: the part of d before p has the extent of fewer columns, p after p."""
    before = [at.all_rows]
    for a in range(at.m):
        before.append(before[-1] & at.columns[a] if a in d else before[-1])
    for p in range(at.m - 1, -1, -1):
        if p not in d:
            extent = before[p] & at.columns[p]
            found = at.intent(extent)
            if all(a >= p or a in d for a in found):
                return found, extent
    return None


def lectic_scan(ctx: FormalContext, max_steps: int | None = None, start: Sequence[str] | None = None, at: LocalContext | None = None) -> DataFrame:
    """step, w0.., size and support of every intent in lectic order, or of those after a given one."""
    at = at or local(ctx)
    found = at.rows().lectic() if start is None else _following(at, frozenset(ctx.rank(n) for n in start), len(ctx.words))
    if max_steps is not None:
        found = islice(found, max_steps + (start is None))
    return _frame(ctx, _numbered(found, len(ctx.words)), "step")


def _following(at: LocalContext, now: frozenset[int], words: int) -> Iterator[tuple[np.ndarray, int]]:
    while (step := successor(at, now)) is not None:
        now, extent = step
        yield np.array(bits.pack(now, words), dtype=np.int64), at.support(extent)


def _numbered(found: Iterator[tuple[np.ndarray, int]], words: int) -> Iterator[Found]:
    """Runs of intents with their places."""
    done = 0
    while some := list(islice(found, AT_ONCE)):
        yield np.array([x for x, _ in some], dtype=np.int64).reshape(-1, words), np.array([s for _, s in some], dtype=np.int64), np.arange(done, done + len(some))
        done += len(some)


def _frame(ctx: FormalContext, found: Iterator[Found], number: str) -> DataFrame:
    """Intents as a table. Long families go to the shared folder run by run, so that the driver holds one run."""
    runs, held, path = [], 0, None
    for words, support, numbers in found:
        runs.append((words, support, numbers))
        held += len(words)
        if held >= AT_ONCE:
            path = path or new_path(ctx.spark, "found")
            _table(ctx, runs, number).write.mode("append").parquet(path)
            runs, held = [], 0
    if path is None:
        return _table(ctx, runs, number)
    if runs:
        _table(ctx, runs, number).write.mode("append").parquet(path)
    return ctx.spark.read.schema(_table(ctx, [], number).schema).parquet(path)


def _table(ctx: FormalContext, runs: list[Found], number: str) -> DataFrame:
    words = np.concatenate([w for w, _, _ in runs]) if runs else np.zeros((0, len(ctx.words)), np.int64)
    support, numbers = (np.concatenate([r[k] for r in runs]) if runs else np.zeros(0, np.int64) for k in (1, 2))
    columns = {number: pa.array(numbers, pa.int32())} | {w: pa.array(words[:, i], pa.int64()) for i, w in enumerate(ctx.words)}
    columns |= {"size": pa.array(np.bitwise_count(words).sum(axis=1), pa.int32()), "support": pa.array(support, pa.int64())}
    return ctx.spark.createDataFrame(pa.table(columns))


def branch_scan(ctx: FormalContext, generator: str = "last", at: LocalContext | None = None) -> DataFrame:
    """level, w0.., size and support.

    "last" adds attributes beyond the last one added, so every intent comes once; "prefix" tries every
    attribute with the part of the intent before it and may find an intent again, each of which is kept
    once."""
    if generator not in ("last", "prefix"):
        raise ValueError(f"no such generator: {generator}")
    at = at or local(ctx)
    if generator == "last":
        return _frame(ctx, ((b.sets, b.more["support"], b.more["level"]) for b in at.rows().walk()), "level")
    first = at.intent(at.all_rows)
    level, found, levels, seen, emitted = [(first, at.all_rows)], [(first, at.support(at.all_rows))], [0], {first}, 1
    depth = 0
    while level:
        depth += 1
        nxt = []
        for d, _ in level:
            for p in range(at.m):
                if p in d:
                    continue
                grown = at.extent([a for a in d if a < p]) & at.columns[p]
                f = at.intent(grown)
                if any(a < p and a not in d for a in f):
                    continue
                emitted += 1
                if f in seen:
                    continue
                seen.add(f)
                nxt.append((f, grown))
                found.append((f, at.support(grown)))
                levels.append(depth)
        level = nxt
    out = _frame(ctx, _packed(found, levels, len(ctx.words)), "level")
    out._emitted = emitted
    return out


def _packed(found: list[tuple[frozenset[int], int]], numbers: list[int], words: int) -> Iterator[Found]:
    yield np.array([bits.pack(d, words) for d, _ in found], dtype=np.int64).reshape(-1, words), np.array([s for _, s in found], dtype=np.int64), np.array(numbers, dtype=np.int64)


def branch_subtrees(ctx: FormalContext, depth: int = 1, most: int = MOST_ROWS) -> DataFrame:
    """w0.. and support: the subtrees below the intents of one level, each finished inside of a task.

    The rows, of a checked size, go to every task."""
    at = local(ctx, most)
    top, level = [], [(at.intent(at.all_rows), at.all_rows, -1)]
    for _ in range(depth):
        top += [(d, at.support(e)) for d, e, _ in level]
        level = [c for d, e, last in level for c in _children(at, d, e, last)]
    words = ctx.words
    roots = ctx.spark.createDataFrame([(k, *bits.pack(d, len(words)), last) for k, (d, _, last) in enumerate(level)], "root int, " + ", ".join(f"{w} long" for w in words) + ", last int")
    schema = ", ".join(f"{w} long" for w in words) + ", support long"

    def finish(t: pa.Table) -> pa.Table:
        out = []
        stack = []
        for row in t.to_pylist():
            d = frozenset(bits.unpack([row[w] for w in words]))
            stack.append((d, at.extent(d), row["last"]))
        while stack:
            d, e, last = stack.pop()
            out.append((*bits.pack(d, len(words)), at.support(e)))
            stack += _children(at, d, e, last)
        return pa.table({c: pa.array([r[i] for r in out], pa.int64()) for i, c in enumerate([*words, "support"])})

    below = roots.groupBy("root").applyInArrow(finish, schema)
    return _frame(ctx, _packed(top, [0] * len(top), len(words)), "level").select(*words, "support").unionByName(below)


def _children(at: LocalContext, d: frozenset[int], extent: int, last: int) -> Iterator[tuple[frozenset[int], int, int]]:
    out = []
    for p in range(last + 1, at.m):
        if p not in d:
            grown = extent & at.columns[p]
            f = at.intent(grown)
            if all(a >= p or a in d for a in f):
                out.append((f, grown, p))
    return out


def brute_force(ctx: FormalContext) -> DataFrame:
    """w0 and support of every closed set, by closing all 2^m attribute sets; for m of 16 at most."""
    if ctx.m > 16:
        raise ValueError("brute force is for 16 attributes at most")
    shift = bits.WORD - max(1, ctx.m)
    subsets = ctx.spark.range(1 << ctx.m).select(F.shiftleft("id", shift).alias("s0") if ctx.m else F.lit(0).cast("long").alias("s0"))
    from galoislake.operators.closure import close

    return close(ctx, subsets, "join").groupBy("w0").agg(F.first("support").alias("support"))
