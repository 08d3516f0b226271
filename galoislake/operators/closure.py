"""Closures of many attribute sets at once: local closures of row parts, merged by intersection.

Three strategies give equal results. "join" broadcasts the seeds to the rows and lets the aggregate of
bitwise AND merge them: its partial step is the local closure, its final step the merge. "blocks" meets
blocks of rows with blocks of seeds, whose common beginnings are looked up once; neither side is collected
or broadcast whole, and both sides of a meeting have a bounded size. "postings" joins seeds and rows by the seed's rarest
attribute, for sparse contexts. `choose` takes join for few seeds and blocks beyond.

A seed that no row contains closes to all attributes with support 0.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from galoislake.functions import bits
from galoislake.operators.context import FormalContext
from galoislake.operators.extents import Rows

FEW_SEEDS = 2_000  # join: seeds broadcast at once, a few words each
ROW_BLOCK, SEED_BLOCK = 32768, 16384
_CELLS = 1 << 22  # rows times attributes of a block
_TASK_SEEDS = 1 << 19


def close(ctx: FormalContext, seeds: DataFrame, strategy: str | None = None, count: int | None = None) -> DataFrame:
    """seeds has s0..; the result has s0.., w0.. (the closure) and support."""
    if strategy is None:
        count = seeds.count() if count is None else count
        strategy = choose(count)
    if strategy == "blocks":
        return _by_blocks(ctx, seeds, count=count)
    return {"join": _by_join, "postings": _by_postings}[strategy](ctx, seeds)


def choose(count: int) -> str:
    return "join" if count <= FEW_SEEDS else "blocks"


def _merged(ctx: FormalContext, seeds: DataFrame, local: DataFrame) -> DataFrame:
    s, w = bits.names_of("s", len(ctx.words)), ctx.words
    bare = seeds.select(*s, *[bits.long(x).alias(c) for c, x in zip(w, ctx.full, strict=True)], bits.long(0).alias("support"))
    met = bare.unionByName(local.select(*s, *w, "support")).groupBy(*s)
    return met.agg(*[F.bit_and(c).alias(c) for c in w], F.sum("support").alias("support"))


def _by_join(ctx: FormalContext, seeds: DataFrame) -> DataFrame:
    s = bits.names_of("s", len(ctx.words))
    inside = bits.contains(ctx.columns(), ctx.columns("s"))
    return _merged(ctx, seeds, ctx.rows.join(F.broadcast(seeds.select(*s)), inside).withColumnRenamed("weight", "support"))


def _cut(fields: list[str], size: int, name: str):
    """Rows of numbers as blocks of bytes, over the borders of batches."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0
        for b in batches:
            if b.num_rows:
                held.append(np.stack([b.column(f).to_numpy() for f in fields], axis=1).astype("<i8"))
                n += b.num_rows
            if n >= size:
                x = np.concatenate(held)
                yield from (_block(x[i : i + size], name) for i in range(0, n - n % size, size))
                held, n = [x[n - n % size :]], n % size
        if n:
            yield _block(np.concatenate(held), name)

    return run


def _block(x: np.ndarray, name: str) -> pa.RecordBatch:
    return pa.RecordBatch.from_pydict({name: pa.array([np.ascontiguousarray(x).tobytes()], pa.binary())})


def row_blocks(ctx: FormalContext, size: int = ROW_BLOCK) -> DataFrame:
    """Static side: one row for each block of packed rows, as bytes."""
    size = max(1, min(size, _CELLS // max(1, ctx.m)))
    rows = ctx.rows.select(*ctx.words, F.col("weight").cast("long"))
    full = max(1, -(-rows.count() // size))  # few full blocks: each of them meets every seed
    return rows.coalesce(full).mapInArrow(_cut([*ctx.words, "weight"], size, "rows"), "rows binary")


def _seed_blocks(ctx: FormalContext, seeds: DataFrame, size: int, count: int | None = None) -> DataFrame:
    """Seeds that differ in their last attribute only lie in one block, as they share work there."""
    s = bits.names_of("s", len(ctx.words))
    tasks = 2 * ctx.spark.sparkContext.defaultParallelism
    if count is not None:
        tasks = max(min(tasks, -(-count // 1024)), -(-count // _TASK_SEEDS))
    begin = bits.without_last(ctx.columns("s"))
    dealt = seeds.select(*s).repartition(tasks, *begin).sortWithinPartitions(*begin)
    return dealt.mapInArrow(_cut(s, size, "seeds"), "seeds binary")


def _by_blocks(ctx: FormalContext, seeds: DataFrame, row_block: int = ROW_BLOCK, seed_block: int = SEED_BLOCK, count: int | None = None) -> DataFrame:
    words, m = len(ctx.words), ctx.m
    s, w = bits.names_of("s", words), ctx.words

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, rows = None, None
        for b in batches:
            for some, asked in zip(b.column("rows"), b.column("seeds"), strict=True):
                packed = some.as_py()
                if packed != last:
                    x = np.frombuffer(packed, "<i8").reshape(-1, words + 1)
                    last, rows = packed, Rows(x[:, :words], x[:, words], m)
                y = np.frombuffer(asked.as_py(), "<i8").reshape(-1, words)
                closure, support = rows.close(y)
                keep = support > 0
                columns = [pa.array(y[keep, k]) for k in range(words)] + [pa.array(closure[keep, k]) for k in range(words)] + [pa.array(support[keep])]
                yield pa.RecordBatch.from_arrays(columns, names=[*s, *w, "support"])

    schema = ", ".join(f"{c} long" for c in [*s, *w, "support"])
    static, asked = row_blocks(ctx, row_block) if ctx.blocks is None else ctx.blocks, _seed_blocks(ctx, seeds, seed_block, count)
    # Blocks meet blocks: the rows of this join are work units of bounded size, made in the tasks that use them.
    return _merged(ctx, seeds, asked.crossJoin(static.hint("shuffle_replicate_nl")).mapInArrow(run, schema))


def _by_postings(ctx: FormalContext, seeds: DataFrame) -> DataFrame:
    s = bits.names_of("s", len(ctx.words))
    dim = ctx.attribute_table().orderBy("support", "rank").select("rank").collect()  # m rows
    rarest = F.coalesce(*[F.when(bits.has_rank(ctx.columns("s"), F.lit(r["rank"])), F.lit(r["rank"])) for r in dim], F.lit(-1)) if dim else F.lit(-1)
    ranks = F.array(F.lit(-1), *[F.when(bits.has_rank(ctx.columns(), F.lit(r["rank"])), F.lit(r["rank"])) for r in dim])
    posted = ctx.rows.select(*ctx.words, F.col("weight").alias("support"), F.explode(F.array_compact(ranks)).alias("rare"))
    local = seeds.select(*s, rarest.alias("rare")).join(posted, "rare").where(bits.contains(ctx.columns(), ctx.columns("s")))
    return _merged(ctx, seeds, local)


def local_closures(ctx: FormalContext, seeds: DataFrame) -> DataFrame:
    """part, s0.., w0..: what each part alone would close a seed to; all attributes where no row of the
    part has the seed. ctx must be split."""
    s, w = bits.names_of("s", len(ctx.words)), ctx.words
    parts = ctx.rows.select("part").distinct()
    met = ctx.rows.join(F.broadcast(seeds.select(*s)), bits.contains(ctx.columns(), ctx.columns("s"))).groupBy("part", *s).agg(*[F.bit_and(c).alias(c) for c in w])
    every = parts.crossJoin(seeds.select(*s))
    return every.join(met, ["part", *s], "left").select("part", *s, *[F.coalesce(F.col(c), bits.long(x)).alias(c) for c, x in zip(w, ctx.full, strict=True)])


def merge_local(ctx: FormalContext, local: DataFrame) -> DataFrame:
    """The closure of each seed from its local closures: they intersect, in any order."""
    s = bits.names_of("s", len(ctx.words))
    return local.groupBy(*s).agg(*[F.bit_and(c).alias(c) for c in ctx.words])
