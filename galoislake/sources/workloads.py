"""Contexts over the given tables, each with the SQL that states the same objects and attributes."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from galoislake.operators.context import FormalContext, build, build_from_pairs
from galoislake.sources import scales as z

# The worked example, and its split into two parts.
TINY = {1: "abdf", 2: "aceg", 3: "bcdfg", 4: "bde", 5: "adef", 6: "bcfg"}
TINY_PARTS = {1: 0, 2: 0, 3: 0, 4: 1, 5: 1, 6: 1}


@dataclass(frozen=True)
class Workload:
    """profiles: (obj, attrs) of a folder of tables. objects and incidence: the same as DuckDB SELECTs,
    of obj, and of obj and name. number: names sort as integers. pairs: (obj, name), for many objects of
    several rows each."""

    name: str
    profiles: Callable[[SparkSession, str], DataFrame]
    objects: str
    incidence: str
    keyed: bool = True
    number: bool = False
    pairs: Callable[[SparkSession, str], DataFrame] | None = None

    def context(self, spark: SparkSession, sf_dir: str) -> FormalContext:
        if self.pairs:
            return build_from_pairs(self.pairs(spark, sf_dir))
        return build(self.profiles(spark, sf_dir), "number" if self.number else "name", keyed=self.keyed)


def _t(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _tiny(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.createDataFrame([(k, list(v)) for k, v in TINY.items()], "obj int, attrs array<string>")


def _lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = _t(spark, sf_dir, "lineitem")
    return t.select(F.concat(
        z.nominal(F.col("l_returnflag"), "flag"), z.nominal(F.col("l_linestatus"), "status"), z.nominal(F.floor((F.col("l_quantity") - 1) / 10).cast("int"), "qty"),
        z.date_part_scale(F.col("l_shipdate"), "year", "year"), z.bands(F.col("l_discount"), (0.035, 0.075), ("low", "mid", "high"), "disc"),
    ).alias("attrs"))


def _part(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = _t(spark, sf_dir, "part")
    name = F.split("p_name", " ")
    return t.select(F.col("p_partkey").alias("obj"), F.concat(z.nominal(F.col("p_brand")), z.nominal(F.col("p_type"), "type"), z.nominal(F.floor((F.col("p_size") - 1) / 10).cast("int"), "size"), z.nominal(F.get(name, 0), "w"), z.nominal(F.get(name, 1), "w")).alias("attrs"))


def _sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    day = F.concat_ws(":", F.col("user_id").cast("string"), F.to_date("ts").cast("string"))
    return _t(spark, sf_dir, "events").withColumn("obj", day)


def _of_groups(rows: DataFrame, attrs) -> DataFrame:
    return rows.select("obj", F.explode_outer(attrs).alias("name")).groupBy("obj").agg(F.collect_set("name").alias("attrs"))


def session_attributes():
    return F.concat(z.nominal(F.col("event_type"), "type"), z.date_part_scale(F.col("ts"), "quarter_of_day", "part"), z.bands(F.col("value"), (5, 15), ("lo", "mid", "hi"), "v"))


def _session_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _of_groups(_sessions(spark, sf_dir), session_attributes())


def _session_keys(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _of_groups(_sessions(spark, sf_dir), z.json_values(F.col("props"), "$.k"))


def _customers(spark: SparkSession, sf_dir: str) -> DataFrame:
    c, o = _t(spark, sf_dir, "customer"), _t(spark, sf_dir, "orders")
    n, r = _t(spark, sf_dir, "nation"), _t(spark, sf_dir, "region")
    own = c.join(n, c["c_nationkey"] == n["n_nationkey"], "left").join(r, n["n_regionkey"] == r["r_regionkey"], "left")
    fixed = own.select(F.col("c_custkey").alias("obj"), F.concat(z.nominal(F.col("c_mktsegment"), "seg"), z.nominal(F.col("r_name"), "region"), z.bands(F.col("c_acctbal"), (0, 5000), ("neg", "mid", "hi"), "bal")).alias("own"))
    seen = z.related(c, o, c["c_custkey"] == o["o_custkey"], F.concat(z.nominal(F.col("o_orderpriority"), "prio"), z.nominal(F.col("o_orderstatus"), "st")), "c_custkey", ("prio=none", "st=none"))
    return fixed.join(seen, "obj").select("obj", F.concat("own", "attrs").alias("attrs"))


def _customer_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _t(spark, sf_dir, "customer").select(F.col("c_custkey").alias("obj"), F.concat(z.nominal(F.col("c_mktsegment"), "seg"), z.bands(F.col("c_acctbal"), (0, 5000), ("neg", "mid", "hi"), "bal")).alias("attrs"))


def _documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    d, lab = _t(spark, sf_dir, "documents"), _t(spark, sf_dir, "labels")
    j = d.join(lab, "doc_id", "left")
    return j.select(F.col("doc_id").alias("obj"), F.concat(z.nominal(F.col("lang"), "lang"), z.nominal(F.col("source"), "src"), z.bands(F.col("n_chars"), (200, 2000), ("s", "m", "l"), "len"), z.nominal(F.col("quality"), "q", "none"), z.nominal(F.col("toxic"), "tox", "none")).alias("attrs"))


def _signs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _t(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("obj"), z.vector_scale(F.col("embedding"), 12).alias("attrs"))


def _conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _of_groups(_t(spark, sf_dir, "conversations").withColumnRenamed("conv_id", "obj"), F.concat(z.nominal(F.col("role"), "role"), z.nominal(F.col("turn"), "turn")))


def _pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _t(spark, sf_dir, "pages").select(F.col("page_id").alias("obj"), z.regex_set(F.col("html"), "<([a-z][a-z0-9]*)").alias("attrs"))


def _suppliers(spark: SparkSession, sf_dir: str) -> DataFrame:
    s, lines, p = _t(spark, sf_dir, "supplier"), _t(spark, sf_dir, "lineitem").where("l_quantity >= 49"), _t(spark, sf_dir, "part")
    big = lines.join(p, lines["l_partkey"] == p["p_partkey"]).select("l_suppkey", "p_brand").distinct()
    return z.related(s, big, s["s_suppkey"] == big["l_suppkey"], z.nominal(F.col("p_brand")), "s_suppkey")


def _nations(spark: SparkSession, sf_dir: str) -> DataFrame:
    n, r = _t(spark, sf_dir, "nation"), _t(spark, sf_dir, "region")
    return n.join(r, n["n_regionkey"] == r["r_regionkey"]).select(F.col("n_nationkey").alias("obj"), z.nominal(F.col("r_name")).alias("attrs"))


def _activity(spark: SparkSession, sf_dir: str) -> DataFrame:
    n, r = _t(spark, sf_dir, "nation"), _t(spark, sf_dir, "region")
    s, c = _t(spark, sf_dir, "supplier"), _t(spark, sf_dir, "customer")
    homes = s.join(n, s["s_nationkey"] == n["n_nationkey"]).join(r, n["n_regionkey"] == r["r_regionkey"]).select(F.col("s_nationkey").alias("k"), F.concat(F.lit("region="), "r_name").alias("name"))
    wants = c.select(F.col("c_nationkey").alias("k"), F.concat(F.lit("seg="), "c_mktsegment").alias("name"))
    both = homes.unionByName(wants).distinct()
    return z.related(n, both, n["n_nationkey"] == both["k"], z.nominal(F.col("name")), "n_nationkey")


def _terms(table: str, key: str) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, sf_dir: z.tokens(_t(spark, sf_dir, table), key, "text")


def _terms_sql(table: str, key: str, top_k: int = 60) -> str:
    each = f"SELECT DISTINCT {key} AS obj, unnest(regexp_extract_all(lower(coalesce(text, '')), '[a-zà-ÿ]+')) AS name FROM {table}"
    return f"""SELECT obj, name FROM ({each}) WHERE name IN (
      SELECT name FROM ({each}) GROUP BY name HAVING count(*) <= greatest(2, CAST(floor(0.05 * (SELECT count(*) FROM {table})) AS BIGINT)) ORDER BY count(*) DESC, name LIMIT {top_k})"""


_DAY = "CAST(user_id AS VARCHAR) || ':' || CAST(CAST(ts AS DATE) AS VARCHAR)"
_BAND = "CASE WHEN {c} < {a} THEN '{x}' WHEN {c} < {b} THEN '{y}' WHEN {c} IS NOT NULL THEN '{z}' END"

WORKLOADS = {
    w.name: w
    for w in (
        Workload("tiny", _tiny, "SELECT unnest([1,2,3,4,5,6]) AS obj", "SELECT obj, unnest(string_split(a, '')) AS name FROM (VALUES " + ",".join(f"({k},'{v}')" for k, v in TINY.items()) + ") AS v(obj, a)"),
        Workload(
            "lineitem_profile", _lineitem, "SELECT row_number() OVER () AS obj FROM lineitem",
            "SELECT obj, unnest(a) AS name FROM (SELECT row_number() OVER () AS obj, ['flag=' || l_returnflag, 'status=' || l_linestatus, 'qty=' || CAST(CAST(floor((l_quantity - 1) / 10) AS INT) AS VARCHAR), 'year=' || CAST(year(l_shipdate) AS VARCHAR), 'disc=' || "
            + _BAND.format(c="l_discount", a=0.035, b=0.075, x="low", y="mid", z="high") + "] AS a FROM lineitem)", keyed=False,
        ),
        Workload("part_traits", _part, "SELECT p_partkey AS obj FROM part", "SELECT p_partkey AS obj, unnest([p_brand, 'type=' || p_type, 'size=' || CAST(CAST(floor((p_size - 1) / 10) AS INT) AS VARCHAR), 'w=' || split_part(p_name, ' ', 1), 'w=' || split_part(p_name, ' ', 2)]) AS name FROM part"),
        Workload("session_mix", _session_mix, f"SELECT DISTINCT {_DAY} AS obj FROM events", f"SELECT {_DAY} AS obj, unnest(['type=' || event_type, 'part=' || CAST(hour(ts) // 6 AS VARCHAR), 'v=' || " + _BAND.format(c="value", a=5, b=15, x="lo", y="mid", z="hi") + "]) AS name FROM events"),
        Workload("session_keys", _session_keys, f"SELECT DISTINCT {_DAY} AS obj FROM events", f"SELECT {_DAY} AS obj, regexp_extract(props, '\"k\": *([0-9]+)', 1) AS name FROM events"),
        Workload(
            "customer_orders", _customers, "SELECT c_custkey AS obj FROM customer",
            "SELECT c_custkey AS obj, unnest(['seg=' || c_mktsegment, 'region=' || r_name, 'bal=' || " + _BAND.format(c="c_acctbal", a=0, b=5000, x="neg", y="mid", z="hi")
            + ", 'prio=' || coalesce(o_orderpriority, 'none'), 'st=' || coalesce(o_orderstatus, 'none')]) AS name FROM customer LEFT JOIN nation ON c_nationkey = n_nationkey LEFT JOIN region ON n_regionkey = r_regionkey LEFT JOIN orders ON o_custkey = c_custkey",
        ),
        Workload("customer_profile", _customer_profile, "SELECT c_custkey AS obj FROM customer", "SELECT c_custkey AS obj, unnest(['seg=' || c_mktsegment, 'bal=' || " + _BAND.format(c="c_acctbal", a=0, b=5000, x="neg", y="mid", z="hi") + "]) AS name FROM customer"),
        Workload(
            "document_meta", _documents, "SELECT doc_id AS obj FROM documents",
            "SELECT d.doc_id AS obj, unnest(['lang=' || lang, 'src=' || source, 'len=' || " + _BAND.format(c="n_chars", a=200, b=2000, x="s", y="m", z="l") + ", 'q=' || coalesce(CAST(quality AS VARCHAR), 'none'), 'tox=' || coalesce(CAST(toxic AS VARCHAR), 'none')]) AS name FROM documents d LEFT JOIN labels l ON l.doc_id = d.doc_id",
        ),
        Workload("embedding_signs", _signs, "SELECT vec_id AS obj FROM embeddings", "SELECT vec_id AS obj, CAST(k AS VARCHAR) AS name FROM embeddings, range(1, 13) r(k) WHERE embedding[k] > 0", number=True),
        Workload("conversation_shape", _conversations, "SELECT DISTINCT conv_id AS obj FROM conversations", "SELECT conv_id AS obj, unnest(['role=' || role, 'turn=' || CAST(turn AS VARCHAR)]) AS name FROM conversations"),
        Workload("page_tags", _pages, "SELECT page_id AS obj FROM pages", "SELECT page_id AS obj, unnest(regexp_extract_all(html, '<([a-z][a-z0-9]*)', 1)) AS name FROM pages"),
        Workload("supplier_brands", _suppliers, "SELECT s_suppkey AS obj FROM supplier", "SELECT l_suppkey AS obj, p_brand AS name FROM lineitem JOIN part ON l_partkey = p_partkey WHERE l_quantity >= 49"),
        Workload("document_terms", _terms("documents", "doc_id"), "SELECT doc_id AS obj FROM documents", _terms_sql("documents", "doc_id")),
        Workload("benchmark_terms", _terms("benchmark", "item_id"), "SELECT item_id AS obj FROM benchmark", _terms_sql("benchmark", "item_id")),
        Workload("nation_region", _nations, "SELECT n_nationkey AS obj FROM nation", "SELECT n_nationkey AS obj, r_name AS name FROM nation JOIN region ON n_regionkey = r_regionkey"),
        Workload("nation_activity", _activity, "SELECT n_nationkey AS obj FROM nation", "SELECT s_nationkey AS obj, 'region=' || r_name AS name FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey UNION SELECT c_nationkey, 'seg=' || c_mktsegment FROM customer"),
    )
}
