"""Scales: how columns of tables become attributes. Each gives an ARRAY<STRING> column; nulls give no
attribute unless null_as names one."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _listed(name: Column, null_as: str | None = None) -> Column:
    named = F.coalesce(name, F.lit(null_as)) if null_as is not None else name
    return F.array_compact(F.array(named))


def nominal(col: Column, label: str = "", null_as: str | None = None) -> Column:
    """One attribute for each value."""
    text = col.cast("string")
    return _listed(F.concat(F.lit(f"{label}="), text) if label else text, f"{label}={null_as}" if null_as is not None and label else null_as)


def bands(col: Column, edges: Sequence[float], names: Sequence[str], label: str = "") -> Column:
    """The band a number falls in: below the first edge, from an edge up to the next, from the last on."""
    out = F.when(col < edges[0], F.lit(names[0]))
    for e, n in zip(edges[1:], names[1:], strict=False):
        out = out.when(col < e, F.lit(n))
    return nominal(out.when(col.isNotNull(), F.lit(names[-1])), label)


def at_least(col: Column, edges: Sequence[float], label: str) -> Column:
    """One attribute for each edge that the value reaches."""
    return F.array_compact(F.array(*[F.when(col >= e, F.lit(f"{label}>={e}")) for e in edges]))


def between_scale(col: Column, edges: Sequence[float], label: str) -> Column:
    """Attributes for both directions."""
    return F.concat(at_least(col, edges, label), F.array_compact(F.array(*[F.when(col <= e, F.lit(f"{label}<={e}")) for e in edges])))


def flag(condition: Column, label: str) -> Column:
    return F.array_compact(F.array(F.when(condition, F.lit(label))))


def date_part_scale(ts: Column, part: str, label: str) -> Column:
    value = {"year": F.year, "month": F.month, "dow": F.dayofweek, "quarter_of_day": lambda t: F.floor(F.hour(t) / 6)}[part](ts)
    return nominal(value, label)


def words(col: Column, pattern: str) -> Column:
    """Distinct lower-case words of a text."""
    return F.array_distinct(F.regexp_extract_all(F.lower(F.coalesce(col, F.lit(""))), F.lit(f"({pattern})"), F.lit(1)))


def frequent_words(table: DataFrame, key: str, text: str, top_k: int, share: float, least: int, pattern: str) -> DataFrame:
    """word: the top_k most frequent of those in at most share of the rows (or `least` rows); ties by word."""
    rows = table.count()
    each = table.select(F.explode(words(F.col(text), pattern)).alias("word"))
    counts = each.groupBy("word").agg(F.count("*").alias("n")).where(F.col("n") <= max(least, int(share * rows)))
    return counts.orderBy(F.desc("n"), "word").limit(top_k).select("word")


def tokens(table: DataFrame, key: str, text: str, top_k: int = 60, share: float = 0.05, least: int = 2, pattern: str = "[a-zà-ÿ]+") -> DataFrame:
    """(obj, attrs): each row's words among the frequent ones. The list of kept words is top_k long."""
    kept = [r.word for r in frequent_words(table, key, text, top_k, share, least, pattern).collect()]
    mine = F.array_intersect(words(F.col(text), pattern), F.array(*[F.lit(w) for w in kept]).cast("array<string>"))
    return table.select(F.col(key).alias("obj"), mine.alias("attrs"))


def json_values(col: Column, path: str, label: str = "") -> Column:
    return nominal(F.get_json_object(col, path), label)


def json_keys(col: Column) -> Column:
    return F.coalesce(F.json_object_keys(col), F.array().cast("array<string>"))


def vector_scale(col: Column, dims: int, threshold: float = 0.0) -> Column:
    """The numbers (from 1) of the first dims components above the threshold."""
    return F.array_compact(F.transform(F.slice(col, 1, dims), lambda x, i: F.when(x > threshold, (i + 1).cast("string"))))


def related(parents: DataFrame, children: DataFrame, on: Column, attrs: Column, key: str, none: Sequence[str] = ()) -> DataFrame:
    """(obj, attrs): the attributes of all related rows; `none` for objects without any."""
    joined = parents.join(children, on, "left").select(F.col(key).alias("obj"), F.explode_outer(attrs).alias("name"))
    found = joined.groupBy("obj").agg(F.collect_set("name").alias("attrs"))
    return found.select("obj", F.when(F.size("attrs") == 0, F.array(*[F.lit(n) for n in none]).cast("array<string>")).otherwise(F.col("attrs")).alias("attrs"))


def regex_set(col: Column, pattern: str) -> Column:
    return F.array_distinct(F.regexp_extract_all(F.coalesce(col, F.lit("")), F.lit(pattern), F.lit(1)))


def map_scale(col: Column) -> Column:
    """One attribute for each entry of a map."""
    return F.transform(F.map_entries(col), lambda e: F.concat(e["key"].cast("string"), F.lit("="), e["value"].cast("string")))


def money(col: Column, label: str, null_as: str | None = None) -> Column:
    """A number by its exact decimal value."""
    return nominal(col.cast("decimal(18,2)"), label, null_as)
