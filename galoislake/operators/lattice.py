"""The order of concepts: covers, neighbours, meets and joins, levels, and families that grow."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from galoislake.functions import bits
from galoislake.operators.closure import close
from galoislake.operators.context import FormalContext
from galoislake.plans.storage import forget, settle, settle_counted


def lower_covers(ctx: FormalContext, intents: DataFrame) -> DataFrame:
    """d0.., w0..: the neighbours below each concept d, as the least closures of d with one attribute
    more. A closure is a neighbour exactly if every attribute it adds leads to it."""
    d = bits.names_of("d", len(ctx.words))
    s = bits.names_of("s", len(ctx.words))
    ranks = ctx.spark.range(ctx.m).select(F.col("id").cast("int").alias("rank"))
    named = intents.select(*[F.col(w).alias(x) for w, x in zip(ctx.words, d, strict=True)])
    tried = named.crossJoin(F.broadcast(ranks)).where(~bits.has_rank(ctx.columns("d"), F.col("rank")))
    tried = tried.select(*d, *[c.alias(x) for c, x in zip(bits.with_bit(ctx.columns("d"), F.col("rank")), s, strict=True)])
    grown = tried.join(close(ctx, tried.select(*s).distinct()), s)
    found = grown.groupBy(*d, *ctx.words).agg(F.count("*").alias("ways"))
    added = bits.size_of([F.col(w).bitwiseAND(F.bitwise_not(F.col(x))) for w, x in zip(ctx.words, d, strict=True)])
    return found.where(F.col("ways") == added).select(*d, *ctx.words)


def covers(ctx: FormalContext, intents: DataFrame) -> DataFrame:
    """child and parent intents as strings; a parent has fewer attributes and more objects."""
    edges = lower_covers(ctx, intents)
    return edges.select(ctx.string().alias("child"), bits.intent_string(ctx.columns("d"), ctx.attributes).alias("parent"))


def levels(ctx: FormalContext, intents: DataFrame) -> DataFrame:
    """size, concepts of that many attributes, and how many have that many or fewer."""
    return running(intents.groupBy(bits.size_of(ctx.columns()).alias("size")).agg(F.count("*").alias("concepts")))


def running(counts: DataFrame) -> DataFrame:
    """size and concepts, with how many have that size or less."""
    from pyspark.sql import Window

    return counts.withColumn("running", F.sum("concepts").over(Window.orderBy("size")))  # at most m + 1 rows


def meets_and_joins(ctx: FormalContext, pairs: DataFrame) -> DataFrame:
    """For intents a0.., b0..: the closure of their union (meet) and their intersection (join)."""
    words = len(ctx.words)
    s = [F.col(f"a{i}").bitwiseOR(F.col(f"b{i}")).alias(f"s{i}") for i in range(words)]
    both = [F.col(f"a{i}").bitwiseAND(F.col(f"b{i}")).alias(f"j{i}") for i in range(words)]
    tried = pairs.select(*bits.names_of("a", words), *bits.names_of("b", words), *s, *both)
    return tried.join(close(ctx, tried.select(*bits.names_of("s", words)).distinct()).drop("support"), bits.names_of("s", words))


ROWS_AT_ONCE = 2_000  # new rows that meet a family together, a few words each


def update_intents(family: DataFrame | None, new_rows: DataFrame, full: tuple[int, ...]) -> DataFrame:
    """The family (words w0..) after objects with the given rows (w0..) arrive.

    A family is closed under intersection, so the new one holds every intersection of an old intent with
    some of the new rows. Passes intersect only the intents of the pass before with the rows, and end when
    nothing new comes; rows beyond ROWS_AT_ONCE wait for a turn of their own."""
    words = bits.names_of("w", len(full))
    rows = settle(new_rows.select(*words).distinct(), "rows")
    if family is None:
        family = rows.sparkSession.createDataFrame([full], ", ".join(f"{w} long" for w in words))
    known = family.select(*words)
    turns = -(-rows.count() // ROWS_AT_ONCE)
    for turn in range(turns):
        some = F.broadcast(rows.where(F.pmod(F.xxhash64(*words), F.lit(turns)) == turn).toDF(*bits.names_of("r", len(words))))
        frontier = known
        while True:
            met = frontier.crossJoin(some).select(*[F.col(w).bitwiseAND(F.col(f"r{i}")).alias(w) for i, w in enumerate(words)])
            frontier, held = settle_counted(met.distinct().join(known, words, "left_anti"), "met")
            if not held["n"]:
                break
            old, known = known, settle(known.unionByName(frontier), "family")
            if old is not family:
                forget(old)
    forget(rows)
    return known


def intersections(rows: DataFrame, full: tuple[int, ...]) -> DataFrame:
    """All intersections of none, one or more of the rows; that of none is the set of all attributes."""
    return update_intents(None, rows, full)


def supports(ctx: FormalContext, intents: DataFrame) -> DataFrame:
    """w0.. and support of given intents."""
    s = bits.names_of("s", len(ctx.words))
    asked = intents.select(*[F.col(w).alias(x) for w, x in zip(ctx.words, s, strict=True)])
    return close(ctx, asked).select(*ctx.words, "support")


def paths_up(ctx: FormalContext, edges: DataFrame, start: DataFrame, most: int = 4096) -> DataFrame:
    """w0.. and steps: every concept above those of `start` (w0..) along cover edges (d0.. above w0..), with
    the least number of steps. A pass for each step; chains are no longer than the attributes are many."""
    words, d = ctx.words, bits.names_of("d", len(ctx.words))
    seen = settle(start.select(*words).distinct().withColumn("steps", F.lit(0)), "up")
    last = seen
    for step in range(1, min(most, ctx.m) + 1):
        above = last.select(*words).join(edges, words).select(*[F.col(x).alias(w) for w, x in zip(words, d, strict=True)]).distinct()
        last, held = settle_counted(above.join(seen, words, "left_anti").withColumn("steps", F.lit(step)), "above")
        if not held["n"]:
            break
        seen = settle(seen.unionByName(last), "up")
    return seen


def stability(ctx: FormalContext, concepts: DataFrame) -> DataFrame:
    """w0.., support, relative support, and separation: the concept's crosses as a share of all crosses in
    the rows of its extent and the columns of its intent."""
    total = ctx.rows.agg(F.sum("weight").alias("objects"))
    s = bits.names_of("s", len(ctx.words))
    asked = concepts.select(*[F.col(w).alias(x) for w, x in zip(ctx.words, s, strict=True)], "support")
    shared = bits.overlap(ctx.columns(), ctx.columns("s"))
    inside = bits.contains(ctx.columns(), ctx.columns("s"))
    crosses = F.sum(F.when(inside, bits.size_of(ctx.columns())).otherwise(shared) * F.col("weight"))
    met = ctx.rows.join(asked, shared > 0).groupBy(*s, "support").agg(crosses.alias("crosses"))
    sized = met.select(*[F.col(x).alias(w) for w, x in zip(ctx.words, s, strict=True)], "support", "crosses").crossJoin(total)
    return sized.select(*ctx.words, "support", (F.col("support") / F.col("objects")).alias("relative"), (F.col("support") * bits.size_of(ctx.columns()) / F.col("crosses")).alias("separation"))
