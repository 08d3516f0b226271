"""The two derivations, their compositions, and the concept test."""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce
from operator import and_

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from galoislake.functions import bits
from galoislake.operators.closure import close
from galoislake.operators.context import FormalContext


def common_attributes(ctx: FormalContext, objects: DataFrame) -> DataFrame:
    """One row w0..: the attributes shared by all given objects (column obj); all attributes for none."""
    met = ctx.objects.join(objects.select("obj").distinct(), "obj", "left_semi")
    return met.agg(*[F.coalesce(F.bit_and(c), bits.long(x)).alias(c) for c, x in zip(ctx.words, ctx.full, strict=True)])


def objects_with(ctx: FormalContext, attributes: Sequence[str]) -> DataFrame:
    """obj of every object that has all given attributes: a filter, local to each part of the rows."""
    want = [bits.long(x) for x in ctx.pack(attributes)]
    return ctx.objects.where(bits.contains(ctx.columns(), want)).select("obj")


def close_objects(ctx: FormalContext, objects: DataFrame) -> DataFrame:
    """obj of every object that has what the given objects share."""
    shared = common_attributes(ctx, objects).select(*[F.col(c).alias(f"s{i}") for i, c in enumerate(ctx.words)])
    return ctx.objects.join(F.broadcast(shared), bits.contains(ctx.columns(), ctx.columns("s"))).select("obj")


def is_concept(ctx: FormalContext, objects: DataFrame, attributes: Sequence[str]) -> bool:
    """Whether each side is exactly what the other one determines."""
    shared = tuple(common_attributes(ctx, objects).first())
    if shared != ctx.pack(attributes):
        return False
    given, found = objects.select("obj").distinct(), objects_with(ctx, attributes)
    return given.exceptAll(found).isEmpty() and found.exceptAll(given).isEmpty()


def bottom_intent(ctx: FormalContext) -> tuple[int, ...]:
    """What all objects share: the closure of the empty set."""
    return tuple(ctx.rows.agg(*[F.coalesce(F.bit_and(c), bits.long(x)) for c, x in zip(ctx.words, ctx.full, strict=True)]).first())


def is_last(ctx: FormalContext, prefix: str = "w") -> Column:
    """Whether a set is that of all attributes, the lectically last intent."""
    return reduce(and_, [c == bits.long(x) for c, x in zip(ctx.columns(prefix), ctx.full, strict=True)])


def local_extents(ctx: FormalContext, intents: DataFrame, part: Column) -> DataFrame:
    """part, w0.. and obj: the objects of each part that have all of an intent."""
    s = bits.names_of("s", len(ctx.words))
    asked = intents.select(*[F.col(w).alias(x) for w, x in zip(ctx.words, s, strict=True)])
    met = ctx.objects.withColumn("part", part).join(asked, bits.contains(ctx.columns(), ctx.columns("s")))
    return met.select("part", "obj", *[F.col(x).alias(w) for w, x in zip(ctx.words, s, strict=True)])


def merge_extents(ctx: FormalContext, local: DataFrame) -> DataFrame:
    """w0.. and obj: the extent over all parts is the union of the parts' extents. Parts hold different
    objects, so no row is dropped and nothing moves."""
    return local.select(*ctx.words, "obj")


def seeds_of(ctx: FormalContext, intents: DataFrame, keep: Sequence[str] = ()) -> DataFrame:
    """All (d, p) with p outside of d: rank and the seed words s0.., beside the columns to keep."""
    ranks = ctx.spark.range(ctx.m).select(F.col("id").cast("int").alias("rank"))
    pairs = intents.crossJoin(F.broadcast(ranks)).where(~bits.has_rank(ctx.columns(), F.col("rank")))
    return pairs.select(*keep, "rank", *[c.alias(f"s{i}") for i, c in enumerate(bits.seed_words(ctx.columns(), F.col("rank")))])


def oplus(ctx: FormalContext, intents: DataFrame) -> DataFrame:
    """d0.., rank, w0.. and support: the closure of every (d before p) with p."""
    d = bits.names_of("d", len(ctx.words))
    named = intents.select(*ctx.words, *[F.col(w).alias(x) for w, x in zip(ctx.words, d, strict=True)])
    seeds = seeds_of(ctx, named, d)
    s = bits.names_of("s", len(ctx.words))
    return seeds.join(close(ctx, seeds.select(*s).distinct()), s).select(*d, "rank", *ctx.words, "support")


def implied(ctx: FormalContext, seeds: DataFrame) -> DataFrame:
    """s0.., w0.., support and i0..: what each attribute set implies beyond itself."""
    extra = [F.col(w).bitwiseAND(F.bitwise_not(F.col(f"s{i}"))).alias(f"i{i}") for i, w in enumerate(ctx.words)]
    return close(ctx, seeds).select("*", *extra)


def with_extents(ctx: FormalContext, intents: DataFrame) -> DataFrame:
    """w0.. and obj: every object in the extent of every intent, one row each."""
    s = bits.names_of("s", len(ctx.words))
    asked = intents.select(*[F.col(w).alias(x) for w, x in zip(ctx.words, s, strict=True)])
    met = ctx.objects.join(asked, bits.contains(ctx.columns(), ctx.columns("s")))
    return met.select("obj", *[F.col(x).alias(w) for w, x in zip(ctx.words, s, strict=True)])


def extents_from_parents(ctx: FormalContext, tree: DataFrame, extents: DataFrame) -> DataFrame:
    """Extents of children (w0.., parent words d0.., the added rank) from their parents' extents: only the
    objects of the parent are tested, and only for the one attribute."""
    d = bits.names_of("d", len(ctx.words))
    parents = extents.select("obj", *[F.col(w).alias(x) for w, x in zip(ctx.words, d, strict=True)])
    rows = ctx.objects.select(F.col("obj"), *[F.col(w).alias(f"o{i}") for i, w in enumerate(ctx.words)])
    met = tree.join(parents, d).join(rows, "obj")
    return met.where(bits.has_rank(ctx.columns("o"), F.col("rank"))).select("obj", *ctx.words)
