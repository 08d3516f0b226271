"""Contexts and families in files: text baskets, cross tables, and Spark's own formats."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from galoislake.functions import bits
from galoislake.operators.context import FormalContext


def write_baskets(profiles: DataFrame, path: str, separator: str = "\t") -> None:
    """One line for each object: its key, then its attributes."""
    profiles.select(F.concat_ws(separator, F.col("obj").cast("string"), F.concat_ws(separator, F.array_sort("attrs")))).write.text(path)


def read_baskets(spark: SparkSession, path: str, separator: str = "\t") -> DataFrame:
    parts = F.split("value", separator)
    names = F.filter(F.slice(parts, F.lit(2), F.greatest(F.size(parts) - 1, F.lit(0))), lambda x: x != "")
    return spark.read.text(path).select(F.get(parts, 0).alias("obj"), names.alias("attrs"))


def read_cross_table(spark: SparkSession, path: str, key: str = "obj", mark: str = "x") -> DataFrame:
    """A CSV with a header: one column for each attribute, marked where the object has it."""
    t = spark.read.csv(path, header=True)
    names = [c for c in t.columns if c != key]
    return t.select(F.col(key).alias("obj"), F.array_compact(F.array(*[F.when(F.col(f"`{c}`") == mark, F.lit(c)) for c in names])).alias("attrs"))


def write_cross_table(ctx: FormalContext, path: str) -> None:
    ctx.cross_table().write.csv(path, header=True)


def roundtrip(profiles: DataFrame, path: str, kind: str) -> DataFrame:
    """profiles written in a format and read again, as (obj string, attrs)."""
    spark = profiles.sparkSession
    rows = profiles.select(F.col("obj").cast("string").alias("obj"), "attrs")
    if kind == "baskets":
        write_baskets(rows, path)
        return read_baskets(spark, path)
    if kind == "csv":
        rows.select("obj", F.concat_ws("|", "attrs").alias("attrs")).write.csv(path, header=True)
        return spark.read.csv(path, header=True, schema="obj string, attrs string").select("obj", F.filter(F.split(F.coalesce("attrs", F.lit("")), "\\|"), lambda x: x != "").alias("attrs"))
    rows.write.format(kind).save(path)
    return spark.read.format(kind).schema("obj string, attrs array<string>").load(path)


def write_concepts(concepts: DataFrame, path: str) -> None:
    """A family, partitioned by the round that found its members."""
    concepts.write.partitionBy("round").parquet(path)


def publish(ctx: FormalContext, concepts: DataFrame, prefix: str = "") -> None:
    """Temporary views for SQL: concepts (intent, names, size, support, words) and context (words, weight)."""
    named = concepts.select(ctx.string().alias("intent"), bits.intent_array(ctx.columns(), ctx.attributes).alias("names"), bits.size_of(ctx.columns()).alias("size"), "support", *ctx.words)
    named.createOrReplaceTempView(f"{prefix}concepts")
    ctx.rows.createOrReplaceTempView(f"{prefix}context")
