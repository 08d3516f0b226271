"""The round engine and the distributed mining methods on it.

Static data, the packed rows, is read once and stays ("cached"), or is read anew in every round
("reload"); dynamic data, the frontier, is a small table written to the shared folder each round. The
driver holds counts, never intents.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.storagelevel import StorageLevel

from galoislake.functions import bits
from galoislake.operators.closure import close, local_closures, merge_local, row_blocks
from galoislake.operators.context import FormalContext
from galoislake.operators.derive import bottom_intent, seeds_of
from galoislake.plans.storage import forget, settle, settle_counted


@dataclass(frozen=True)
class MiningResult:
    """concepts: round, w0.., size and support; metrics: one tuple for each round."""

    context: FormalContext
    concepts: DataFrame
    metrics: tuple[dict, ...]

    @property
    def rounds(self) -> int:
        return len(self.metrics)

    @property
    def productive_rounds(self) -> int:
        return sum(1 for m in self.metrics if m["new"])

    def strings(self) -> DataFrame:
        """intent, size and support."""
        return self.concepts.select(self.context.string().alias("intent"), bits.size_of(self.context.columns()).alias("size"), "support")

    def metrics_frame(self) -> DataFrame:
        schema = "round int, pairs long, seeds long, new long, merges long, elapsed_s double"
        return self.context.spark.createDataFrame([tuple(m[k] for k in ("round", "pairs", "seeds", "new", "merges", "elapsed_s")) for m in self.metrics], schema)


class TooManyIntents(RuntimeError):
    """The family outgrew max_intents; nothing is cut off in silence."""


def _prepared(ctx: FormalContext, static: str) -> FormalContext:
    if static == "cached":
        kept = replace(ctx, rows=ctx.rows.persist(StorageLevel.MEMORY_AND_DISK), blocks=None)
        return replace(kept, blocks=row_blocks(kept).persist(StorageLevel.MEMORY_AND_DISK))
    if static != "reload":
        raise ValueError(f"no such static mode: {static}")
    return ctx


def _start(ctx: FormalContext) -> DataFrame:
    """The closure of the empty set, with its support."""
    first = ctx.spark.createDataFrame([bottom_intent(ctx)], ", ".join(f"{w} long" for w in ctx.words))
    total = ctx.rows.agg(F.coalesce(F.sum("weight"), F.lit(0)).cast("long").alias("support"))
    return first.crossJoin(total)


class Registry:
    """Intents seen so far, in one table for each round.

    two_level keys the probe by leading attribute, then size, before the words; flat by the words alone;
    none forgets earlier rounds (for ablation, with a cap on rounds)."""

    def __init__(self, ctx: FormalContext, kind: str = "two_level"):
        if kind not in ("two_level", "flat", "none"):
            raise ValueError(f"no such registry: {kind}")
        self.ctx, self.kind, self.tables = ctx, kind, []

    def _keyed(self, df: DataFrame) -> DataFrame:
        return df.withColumns({"head": bits.head_of(self.ctx.columns(), self.ctx.m), "size": bits.size_of(self.ctx.columns())})

    def unseen(self, df: DataFrame) -> DataFrame:
        if self.kind == "none" or not self.tables:
            return df
        seen = self.tables[0]
        for t in self.tables[1:]:
            seen = seen.unionByName(t)
        if self.kind == "flat":
            return df.join(seen, self.ctx.words, "left_anti")
        return self._keyed(df).join(self._keyed(seen), ["head", "size", *self.ctx.words], "left_anti").drop("head", "size")

    def add(self, df: DataFrame) -> None:
        self.tables.append(df.select(*self.ctx.words))


def _collected(ctx: FormalContext, found: list[tuple[int, DataFrame]]) -> DataFrame:
    out = None
    for r, df in found:
        part = df.select(F.lit(r).alias("round"), *ctx.words, bits.size_of(ctx.columns()).alias("size"), "support")
        out = part if out is None else out.unionByName(part)
    return out


def round_all(ctx: FormalContext, parts: int | None = None, registry: str = "two_level", dedupe_seeds: bool = True, max_rounds: int | None = None, static: str = "cached", strategy: str | None = None, min_support: int = 0, max_size: int | None = None, max_intents: int | None = None) -> MiningResult:
    """Every unseen intent is kept in every round and seeds the next one.

    min_support and max_size prune the frontier; both are safe, as every intent within the bounds is
    reached over intents within them."""
    ctx = _prepared(ctx.split(parts) if parts else ctx, static)
    if registry == "none" and max_rounds is None:
        raise ValueError("without a registry, rounds need a cap")
    keep = _bounds(ctx, min_support, max_size)
    open_ranks = F.lit(ctx.m) - bits.size_of(ctx.columns())
    new, held = settle_counted(_start(ctx).where(keep), "round", pairs=open_ranks)
    seen, found, metrics = Registry(ctx, registry), [(0, new)], []
    seen.add(new)
    count = total = held["n"]
    s = bits.names_of("s", len(ctx.words))
    while count and (max_rounds is None or len(metrics) < max_rounds):
        began = time.time()
        pairs = seeds_of(ctx, new)
        seeds, asked_for = settle_counted(pairs.select(*s).distinct() if dedupe_seeds else pairs.select(*s), "seeds")
        asked = asked_for["n"]
        if not asked:
            metrics.append(_metric(len(metrics) + 1, 0, 0, 0, ctx, began))
            break
        closed = _closed_each(ctx, seeds, strategy, asked, dedupe_seeds).where(keep)
        fresh = seen.unseen(closed.groupBy(*ctx.words).agg(F.first("support").alias("support")))
        tried = held["pairs"]
        new, held = settle_counted(fresh.select(*ctx.words, "support"), "round", pairs=open_ranks)
        forget(seeds)
        count = held["n"]
        total += count
        metrics.append(_metric(len(metrics) + 1, tried, asked, count, ctx, began))
        if count:
            seen.add(new)
            found.append((len(metrics), new))
        if max_intents is not None and total > max_intents:
            raise TooManyIntents(f"{total} intents after round {len(metrics)}")
    return _done(ctx, _collected(ctx, found), metrics, static)


def _done(ctx: FormalContext, concepts: DataFrame, metrics: list[dict], static: str) -> MiningResult:
    if static == "cached":
        ctx.rows.unpersist()
        ctx.blocks.unpersist()
        ctx = replace(ctx, blocks=None)
    return MiningResult(ctx, concepts, tuple(metrics))


def _closed_each(ctx: FormalContext, seeds: DataFrame, strategy: str | None, asked: int, distinct: bool) -> DataFrame:
    """Closures of all seeds; repeated seeds are closed again where duplicates were kept on purpose."""
    if distinct:
        return close(ctx, seeds, strategy, asked)
    s = bits.names_of("s", len(ctx.words))
    numbered = seeds.withColumn("_copy", F.monotonically_increasing_id())
    met = ctx.rows.join(numbered, bits.contains(ctx.columns(), ctx.columns("s")))
    local = met.groupBy("_copy", *s).agg(*[F.bit_and(c).alias(c) for c in ctx.words], F.sum("weight").alias("support"))
    full = [F.coalesce(F.col(c), bits.long(x)).alias(c) for c, x in zip(ctx.words, ctx.full, strict=True)]
    return numbered.join(local, ["_copy", *s], "left").select(*full, F.coalesce("support", F.lit(0)).cast("long").alias("support"))


def _bounds(ctx: FormalContext, min_support: int, max_size: int | None):
    keep = F.col("support") >= min_support
    return keep if max_size is None else keep & (bits.size_of(ctx.columns()) <= max_size)


def _metric(r: int, pairs: int, seeds: int, new: int, ctx: FormalContext, began: float) -> dict:
    return {"round": r, "pairs": pairs, "seeds": seeds, "new": new, "merges": ctx.parts * seeds, "elapsed_s": time.time() - began}


def round_branch(ctx: FormalContext, parts: int | None = None, static: str = "cached", strategy: str | None = None, min_support: int = 0, max_rounds: int | None = None) -> MiningResult:
    """Every intent is generated once: an attribute beyond the last one is added and closed, and the
    closure is kept if it adds nothing before that attribute. No registry is needed."""
    ctx = _prepared(ctx.split(parts) if parts else ctx, static)
    s, d = bits.names_of("s", len(ctx.words)), bits.names_of("d", len(ctx.words))
    new, held = settle_counted(_start(ctx).where(F.col("support") >= min_support).withColumn("last", F.lit(-1)), "round")
    found, metrics = [(0, new)], []
    count = held["n"]
    ranks = ctx.spark.range(ctx.m).select(F.col("id").cast("int").alias("rank"))
    while count and (max_rounds is None or len(metrics) < max_rounds):
        began = time.time()
        pairs = new.crossJoin(F.broadcast(ranks)).where((F.col("rank") > F.col("last")) & ~bits.has_rank(ctx.columns(), F.col("rank")))
        tried, held = settle_counted(pairs.select("rank", *[F.col(w).alias(x) for w, x in zip(ctx.words, d, strict=True)], *[c.alias(x) for c, x in zip(bits.with_bit(ctx.columns(), F.col("rank")), s, strict=True)]), "tried")
        asked = held["n"]
        if not asked:
            metrics.append(_metric(len(metrics) + 1, 0, 0, 0, ctx, began))
            break
        closed = close(ctx, tried.select(*s).distinct(), strategy, asked)
        kept = tried.join(closed, s).where(bits.same_before(ctx.columns(), ctx.columns("d"), F.col("rank")) & (F.col("support") >= min_support))
        new, held = settle_counted(kept.select(*ctx.words, "support", F.col("rank").alias("last")), "round")
        forget(tried)
        count = held["n"]
        metrics.append(_metric(len(metrics) + 1, asked, asked, count, ctx, began))
        if count:
            found.append((len(metrics), new))
    return _done(ctx, _collected(ctx, found), metrics, static)


LONG_RUN = 5_000


def round_single(ctx: FormalContext, parts: int = 2, max_rounds: int | None = None, certify: bool = False, static: str = "cached", start: tuple[int, ...] | None = None) -> MiningResult:
    """One intent is accepted in every round: the lectically next one.

    Local closures stay visible by part; those of one attribute merge, and of the feasible results the
    one of the largest attribute wins. certify first closes all seeds in part 0 alone: the closure is a
    subset of the local one, so an attribute whose local closure adds nothing before it is feasible, and
    the seeds of lower attributes are never closed in the other parts."""
    if max_rounds is None and ctx.m * ctx.rows.count() > LONG_RUN:
        raise ValueError("a round for each concept: give max_rounds for a context of this size")
    ctx = _prepared(ctx if "part" in ctx.rows.columns else ctx.split(parts), static)
    words, spark = ctx.words, ctx.spark
    schema = ", ".join(f"{w} long" for w in words)
    d = start or bottom_intent(ctx)
    steps, metrics = [d], []
    while d != ctx.full and (max_rounds is None or len(metrics) < max_rounds):
        began = time.time()
        now = spark.createDataFrame([d], schema)
        seeds = seeds_of(ctx, now)
        names, current = bits.names_of("s", len(words)), [bits.long(x) for x in d]
        if certify:
            first = replace(ctx, rows=ctx.rows.where(F.col("part") == 0), blocks=None)
            proven = local_closures(first, seeds).join(F.broadcast(seeds), names).where(bits.lectic_less_at(current, ctx.columns(), F.col("rank"))).agg(F.max("rank")).first()[0]
            seeds = seeds.where(F.col("rank") >= F.lit(-1 if proven is None else proven))
        ranked = local_closures(ctx, seeds).join(F.broadcast(seeds), names)
        merged = ranked.groupBy("rank").agg(*[F.bit_and(c).alias(c) for c in words])
        best = merged.where(bits.lectic_less_at(current, ctx.columns(), F.col("rank"))).orderBy(F.desc("rank")).limit(1).first()
        asked = ctx.m - sum(x.bit_count() for x in d)
        d = tuple(best[w] for w in words)
        steps.append(d)
        metrics.append(_metric(len(metrics) + 1, asked, asked, 1, ctx, began))
    s = bits.names_of("s", len(words))
    numbered = spark.createDataFrame([(i, *x) for i, x in enumerate(steps)], "round int, " + ", ".join(f"{x} long" for x in s))
    closed = close(ctx, numbered.select(*s).distinct()).select(*s, "support")
    concepts = numbered.join(closed, s).select("round", *[F.col(x).alias(w) for x, w in zip(s, words, strict=True)], "support").withColumn("size", bits.size_of(ctx.columns()))
    return _done(ctx, settle(concepts.select("round", *words, "size", "support"), "steps"), metrics, static)


def trace(ctx: FormalContext, intents: DataFrame) -> DataFrame:
    """d, p, one local closure for each part, the merged closure and whether p is feasible for d."""
    d, s = bits.names_of("d", len(ctx.words)), bits.names_of("s", len(ctx.words))
    named = intents.select(*ctx.words, *[F.col(w).alias(x) for w, x in zip(ctx.words, d, strict=True)])
    pairs = seeds_of(ctx, named, d)
    local = local_closures(ctx, pairs.select(*s).distinct())
    merged = merge_local(ctx, local)
    shown = local.groupBy(*s).pivot("part", list(range(ctx.parts))).agg(F.first(ctx.string()))
    shown = shown.select(*s, *[F.col(str(k)).alias(f"local{k + 1}") for k in range(ctx.parts)])
    name = F.element_at(F.array(*[F.lit(a) for a in ctx.attributes]), F.col("rank") + 1)
    out = pairs.join(merged, s).join(shown, s)
    return out.select(bits.intent_string(ctx.columns("d"), ctx.attributes).alias("d"), name.alias("p"), *[f"local{k + 1}" for k in range(ctx.parts)], ctx.string().alias("merged"), bits.lectic_less_at(ctx.columns("d"), ctx.columns(), F.col("rank")).alias("feasible"))
