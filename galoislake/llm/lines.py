"""Line dedup by distinct-site spread, in DataFrame operations only.

A line is boilerplate when it stands on at least `min_sites` distinct sites (the source column). Each
line hash gets a HyperLogLog sketch of its sites; partial sketches merge in the aggregation, so a line
with a third of all rows moves one sketch a task. Estimates clear of the threshold decide alone; lines
within `margin` of it get an exact distinct count in a second aggregation. Boilerplate lines are then
cut from every text.

Every document is cut, whatever share of it goes. With spare_copies (for a near-duplicate stage after
this one) a document of which nothing but blanks would be left keeps its text: every copy of a text on
min_sites sites is one, and cutting all of them would lose the text itself.

Defined results: a null text stays null with no lines; an empty text has one empty line; lines of
blanks are never cut; a null site counts for no site; repeated rows are treated alike; an empty table
gives no rows. All other columns are kept; the names that begin with _ld_ are reserved.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from galoislake.llm.common import settle, table

MIN_SITES = 10
MARGIN = 0.1  # six standard errors of a sketch of 4096 registers
SALTS = 64  # keys of one text, which may be that of a third of all rows
_LG = 12


def _split(text: Column) -> Column:
    return F.split(text, "\n", -1)


def _hashed(line: Column) -> list[Column]:
    """128 bits: two chains of one hash function, the second begun with another value."""
    return [F.xxhash64(line).alias("_ld_a"), F.xxhash64(F.lit(1), line).alias("_ld_b")]


def boilerplate(docs: DataFrame, min_sites: int = MIN_SITES, margin: float = MARGIN, *, text: str = "text", site: str = "source") -> DataFrame:
    """Hashes (_ld_a, _ld_b) of the lines on at least min_sites distinct sites."""
    lines = docs.where(F.col(text).isNotNull() & F.col(site).isNotNull()).select(F.col(site).cast("string").alias("site"), F.explode(F.array_distinct(_split(F.col(text)))).alias("line")).where(F.length(F.trim("line")) > 0).select("site", *_hashed(F.col("line")))
    key = ["_ld_a", "_ld_b"]
    spread = lines.groupBy(*key).agg(F.hll_sketch_agg("site", _LG).alias("sketch")).select(*key, F.hll_sketch_estimate("sketch").alias("sites"))
    known = settle(spread.where(F.col("sites") > min_sites * (1 - margin)), "spread")
    sure = known.where(F.col("sites") >= min_sites * (1 + margin)).select(*key)
    near = known.where(F.col("sites") < min_sites * (1 + margin)).select(*key)
    exact = lines.join(near, key, "left_semi").groupBy(*key).agg(F.count_distinct("site").alias("sites")).where(F.col("sites") >= min_sites).select(*key)
    return settle(sure.unionByName(exact), "boilerplate")


def cut_boilerplate(docs: DataFrame, min_sites: int = MIN_SITES, margin: float = MARGIN, *, spare_copies: bool = False, text: str = "text", site: str = "source", counts: bool = False) -> DataFrame:
    """docs with the boilerplate lines cut from the text column; with counts, also n_lines and n_cut, which
    replace columns of those names."""
    if counts:
        docs = docs.drop("n_lines", "n_cut")
    bad = boilerplate(docs, min_sites, margin, text=text, site=site)
    others = [F.col(f"`{c}`") for c in docs.columns if c != text]
    # Equal texts lose equal lines; the copies of one text are dealt by their other columns.
    identity = F.concat(F.unhex(F.md5(F.col(text))), F.chr(F.pmod(F.xxhash64(*others), F.lit(SALTS))).cast("binary"))
    lines = docs.where(F.col(text).isNotNull()).select(identity.alias("_ld_key"), F.posexplode(_split(F.col(text))).alias("_ld_at", "_ld_line"))
    found = lines.select("_ld_key", "_ld_at", *_hashed(F.col("_ld_line"))).join(bad, ["_ld_a", "_ld_b"])
    cuts = found.groupBy("_ld_key").agg(F.collect_set("_ld_at").alias("_ld_cut"))
    joined = docs.withColumn("_ld_key", identity).join(cuts, "_ld_key", "left")
    cut = F.array_join(F.filter(_split(F.col(text)), lambda _, i: ~F.array_contains("_ld_cut", i)), "\n")
    applied = F.col("_ld_cut").isNotNull()
    if spare_copies:
        applied &= F.col("_ld_new").rlike(r"\S")
    out = joined.withColumn("_ld_new", F.when(F.col("_ld_cut").isNotNull(), cut))
    shown = [F.when(applied, F.col("_ld_new")).otherwise(F.col(text)).alias(text) if c == text else F.col(f"`{c}`") for c in docs.columns]
    if counts:
        shown += [F.coalesce(F.size(_split(F.col(text))), F.lit(0)).cast("long").alias("n_lines"), F.when(applied, F.size("_ld_cut")).otherwise(0).cast("long").alias("n_cut")]
    return out.select(*shown)


def op8_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "source")
    return cut_boilerplate(docs, counts=True)


def cleaned_sql(docs: str, min_sites: int = MIN_SITES) -> str:
    """A SELECT of doc_id, text, source, n_lines and n_cut over a table with doc_id, text and source."""
    return f"""
SELECT d.doc_id, CASE WHEN c.n > 0 THEN c.kept ELSE d.text END AS text, d.source,
       coalesce(len(string_split(d.text, chr(10))), 0) AS n_lines, coalesce(c.n, 0) AS n_cut
FROM {docs} d LEFT JOIN (
  SELECT l.doc_id, coalesce(string_agg(l.line, chr(10) ORDER BY l.at) FILTER (WHERE b.line IS NULL), '') AS kept, count(b.line) AS n
  FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS at FROM {docs}) l
  LEFT JOIN (
    SELECT line FROM (SELECT source, unnest(string_split(text, chr(10))) AS line FROM {docs})
    WHERE length(trim(line, ' ')) > 0 GROUP BY line HAVING count(DISTINCT source) >= {min_sites}
  ) b ON l.line = b.line GROUP BY l.doc_id
) c ON c.doc_id = d.doc_id"""


SQL = cleaned_sql("documents")
