"""Formal contexts: an ordered attribute list on the driver, packed distinct rows as a table.

Rows that are equal are kept once with a weight: closures are intersections and need each row once,
supports sum the weights. The attribute list is small by nature and its length is checked.

Null names count as no attribute; a repeated (object, attribute) pair counts once; an object without
attributes is an empty row; a context without objects has every attribute set closed to all attributes.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from galoislake.functions import bits
from galoislake.plans.storage import settle

MOST_ATTRIBUTES = 4096


@dataclass(frozen=True)
class FormalContext:
    """rows: w0.. and weight, distinct; objects: obj and w0.., or None where objects have no key."""

    attributes: tuple[str, ...]
    rows: DataFrame
    objects: DataFrame | None = None
    parts: int = 1
    blocks: DataFrame | None = None  # the rows as kept blocks, while a method runs

    @property
    def spark(self) -> SparkSession:
        return self.rows.sparkSession

    @property
    def m(self) -> int:
        return len(self.attributes)

    @property
    def words(self) -> list[str]:
        return bits.names_of("w", bits.width(self.m))

    @property
    def full(self) -> tuple[int, ...]:
        return bits.full_words(self.m)

    def columns(self, prefix: str = "w") -> list[Column]:
        return [F.col(c) for c in bits.names_of(prefix, bits.width(self.m))]

    def rank(self, name: str) -> int:
        return self.attributes.index(name)

    def pack(self, names: Sequence[str]) -> tuple[int, ...]:
        return bits.pack([self.rank(n) for n in names], bits.width(self.m))

    def sets(self, sets: Sequence[Sequence[str]]) -> DataFrame:
        """Attribute sets given by name, as a table of words."""
        schema = ", ".join(f"{w} long" for w in self.words)
        return self.spark.createDataFrame([self.pack(s) for s in sets], schema)

    def string(self, prefix: str = "w") -> Column:
        return bits.intent_string(self.columns(prefix), self.attributes)

    def attribute_table(self) -> DataFrame:
        """rank, name, support, word and mask of every attribute."""
        rows = [(r, n, bits.mask(r)[0], bits.mask(r)[1]) for r, n in enumerate(self.attributes)]
        dim = self.spark.createDataFrame(rows, "rank int, name string, word int, mask long")
        if not rows:
            return dim.withColumn("support", F.lit(0).cast("long"))
        pairs = self.rows.select("weight", F.explode(bits.intent_array(self.columns(), self.attributes)).alias("name"))
        support = pairs.groupBy("name").agg(F.sum("weight").alias("support"))
        return dim.join(support, "name", "left").select("rank", "name", F.coalesce("support", F.lit(0)).cast("long").alias("support"), "word", "mask")

    def split(self, parts: int, how: str = "hash") -> FormalContext:
        """The same context in disjoint parts of rows, numbered in the column part.

        hash deals rows by their words, block in runs of lectic order, round_robin in turn, density in
        turn over rows sorted by size, back and forth, so that parts get equally dense."""
        words, size = self.words, bits.size_of(self.columns())
        if how == "hash":
            dealt = self.rows.withColumn("part", F.pmod(F.xxhash64(*words), F.lit(parts)).cast("int"))
        elif how in ("block", "round_robin", "density"):
            # Places are exact without a global window: sizes of sorted ranges, summed on the driver.
            order = [F.col(w) for w in words] if how != "density" else [size, *[F.col(w) for w in words]]
            dealt = _numbered(self.rows, order)
            total = F.lit(max(1, self.rows.count()))
            turn = F.pmod("place", F.lit(2 * parts))
            part = {"block": F.floor(F.col("place") * parts / total), "round_robin": F.pmod("place", F.lit(parts)), "density": F.when(turn < parts, turn).otherwise(2 * parts - 1 - turn)}[how]
            dealt = dealt.withColumn("part", part.cast("int")).drop("place")
        else:
            raise ValueError(f"no such split: {how}")
        return replace(self, rows=settle(dealt.repartition(parts, "part"), "parts"), parts=parts)

    def sample(self, share: float, seed: int = 7) -> FormalContext:
        """A context of about that share of the distinct rows, the same ones every time. Its intents are
        intents of this context too, as both are intersections of rows, so its family is a lower bound."""
        kept = F.pmod(F.xxhash64(F.lit(seed), *self.words), F.lit(1_000_000)) < int(share * 1_000_000)
        return replace(self, rows=settle(self.rows.where(kept), "sample"), objects=None if self.objects is None else self.objects.where(kept))

    def partition_profile(self) -> DataFrame:
        """part, rows, objects, crosses and density."""
        crosses = F.sum(bits.size_of(self.columns()) * F.col("weight"))
        own = self.rows if "part" in self.rows.columns else self.rows.withColumn("part", F.lit(0))
        counted = own.groupBy("part").agg(F.count("*").alias("rows"), F.sum("weight").alias("objects"), crosses.cast("long").alias("crosses"))
        return counted.withColumn("density", F.col("crosses") / (F.col("objects") * max(1, self.m)))

    def profile(self) -> DataFrame:
        """objects, attributes, crosses, density and distinct rows, as one row."""
        got = self.rows.agg(F.coalesce(F.sum("weight"), F.lit(0)).cast("long").alias("objects"), F.lit(self.m).cast("long").alias("attributes"), F.coalesce(F.sum(bits.size_of(self.columns()) * F.col("weight")), F.lit(0)).cast("long").alias("crosses"), F.count("*").alias("distinct_rows"))
        return got.withColumn("density", F.when((F.col("objects") > 0) & (F.col("attributes") > 0), F.col("crosses") / (F.col("objects") * F.col("attributes"))).otherwise(F.lit(0.0)))

    def cross_table(self) -> DataFrame:
        """One column for each attribute, x where an object has it."""
        marks = [F.when(self.columns()[bits.mask(r)[0]].bitwiseAND(bits.long(bits.mask(r)[1])) != 0, F.lit("x")).otherwise("").alias(n) for r, n in enumerate(self.attributes)]
        return self.objects.select("obj", *marks)

    def incidence(self) -> DataFrame:
        return self.objects.select("obj", F.explode(bits.intent_array(self.columns(), self.attributes)).alias("name"))


def _numbered(rows: DataFrame, order: list[Column]) -> DataFrame:
    """rows with their place in a total order, from 0."""
    placed = settle(rows.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_run", F.spark_partition_id()).withColumn("_at", F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1))), "placed")
    sizes = {r["_run"]: r["n"] for r in placed.groupBy("_run").agg(F.count("*").alias("n")).collect()}  # one row for each range
    before, total = [], 0
    for run in sorted(sizes):
        before.append((run, total))
        total += sizes[run]
    if not before:
        return rows.withColumn("place", F.lit(0).cast("long"))
    offsets = rows.sparkSession.createDataFrame(before, "_run int, _before long")
    return placed.join(F.broadcast(offsets), "_run").withColumn("place", F.col("_at") + F.col("_before")).drop("_run", "_at", "_before")


def build(profiles: DataFrame, order: str = "name", explicit: Sequence[str] | None = None, keyed: bool = True) -> FormalContext:
    """A context from rows of (obj, attrs ARRAY<STRING>); without keyed, attrs alone.

    order: name, number (names as integers), support, support_desc, or explicit for the given list."""
    attrs = F.array_sort(F.array_distinct(F.array_compact(F.coalesce("attrs", F.array().cast("array<string>")))))
    clean = profiles.select(*(["obj"] if keyed else []), attrs.alias("attrs"))
    distinct = settle(clean.groupBy("attrs").agg(F.count("*").alias("weight")), "profiles")
    if explicit is None:
        counts = _few(distinct.select("weight", F.explode("attrs").alias("name")).groupBy("name").agg(F.sum("weight").alias("support")))
        key = {"name": lambda r: r["name"].encode(), "number": lambda r: int(r["name"]), "support": lambda r: (r["support"], r["name"].encode()), "support_desc": lambda r: (-r["support"], r["name"].encode())}[order]
        explicit = [r["name"] for r in sorted(counts, key=key)]
    attributes = tuple(explicit)
    words = [c.alias(f"w{i}") for i, c in enumerate(bits.packed_from_array(F.col("attrs"), attributes))]
    names = bits.names_of("w", len(words))
    rows = settle(distinct.select(*words, "weight").groupBy(*names).agg(F.sum("weight").alias("weight")), "rows")
    return FormalContext(attributes, rows, clean.select("obj", *words) if keyed else None)


def _few(names: DataFrame) -> list:
    counts = names.limit(MOST_ATTRIBUTES + 1).collect()
    if len(counts) > MOST_ATTRIBUTES:
        raise ValueError(f"more than {MOST_ATTRIBUTES} attributes")
    return counts


def build_from_pairs(pairs: DataFrame) -> FormalContext:
    """A context, in order of names, from rows of (obj, name); a null name keeps an object without attributes.

    Sets are packed while objects are grouped, so no list of names is ever made for an object."""
    spark = pairs.sparkSession
    attributes = tuple(sorted((r["name"] for r in _few(pairs.select("name").where(F.col("name").isNotNull()).distinct())), key=str.encode))
    words = bits.names_of("w", bits.width(len(attributes)))
    dim = spark.createDataFrame([(n, *bits.pack([r], len(words))) for r, n in enumerate(attributes)], "name string, " + ", ".join(f"{w} long" for w in words))
    own = pairs.join(F.broadcast(dim), "name", "left").groupBy("obj")
    objects = own.agg(*[F.coalesce(F.bit_or(w), bits.long(0)).alias(w) for w in words])
    rows = settle(objects.groupBy(*words).agg(F.count("*").alias("weight")), "rows")
    return FormalContext(attributes, rows, objects.select("obj", *words))
