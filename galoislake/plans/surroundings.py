"""Queries around the mining methods: scales, groupings, joins, SQL functions and file formats.

Each entry is (query(spark, sf_dir, context, mined), SQL)."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from galoislake.functions import bits, sqlapi
from galoislake.plans import oracle
from galoislake.plans.storage import new_path
from galoislake.sources import files
from galoislake.sources import scales as z
from galoislake.sources.workloads import WORKLOADS

QUERIES: dict[str, tuple] = {}


def _read(spark, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _scale(name: str, table: str, key: str, column, sql: str) -> None:
    query = lambda spark, sf_dir, *_: _read(spark, sf_dir, table).select(F.col(key).alias("obj"), F.explode(column()).alias("name")).distinct()
    QUERIES[f"scale_{name}"] = (query, f"SELECT DISTINCT obj, name FROM ({sql}) WHERE name IS NOT NULL")


_scale("nominal", "orders", "o_orderkey", lambda: z.nominal(F.col("o_orderpriority"), "prio"), "SELECT o_orderkey AS obj, 'prio=' || o_orderpriority AS name FROM orders")
_scale("bands", "customer", "c_custkey", lambda: z.bands(F.col("c_acctbal"), (0, 5000), ("neg", "mid", "hi"), "bal"), "SELECT c_custkey AS obj, 'bal=' || CASE WHEN c_acctbal < 0 THEN 'neg' WHEN c_acctbal < 5000 THEN 'mid' ELSE 'hi' END AS name FROM customer")
_scale("at_least", "part", "p_partkey", lambda: z.at_least(F.col("p_size"), (10, 20, 30, 40), "size"), "SELECT p_partkey AS obj, 'size>=' || e AS name FROM part, (VALUES (10), (20), (30), (40)) v(e) WHERE p_size >= e")
_scale("between", "part", "p_partkey", lambda: z.between_scale(F.col("p_size"), (10, 25, 40), "size"), "SELECT p_partkey AS obj, 'size>=' || e AS name FROM part, (VALUES (10), (25), (40)) v(e) WHERE p_size >= e UNION ALL SELECT p_partkey, 'size<=' || e FROM part, (VALUES (10), (25), (40)) v(e) WHERE p_size <= e")
_scale("flag", "labels", "doc_id", lambda: F.concat(z.flag(F.col("toxic") == 1, "toxic"), z.flag(F.col("quality") == 1, "good")), "SELECT doc_id AS obj, 'toxic' AS name FROM labels WHERE toxic = 1 UNION ALL SELECT doc_id, 'good' FROM labels WHERE quality = 1")
_scale("calendar", "orders", "o_orderkey", lambda: F.concat(z.date_part_scale(F.col("o_orderdate"), "year", "year"), z.date_part_scale(F.col("o_orderdate"), "month", "month"), z.date_part_scale(F.col("o_orderdate"), "dow", "dow")), "SELECT o_orderkey AS obj, unnest(['year=' || year(o_orderdate), 'month=' || month(o_orderdate), 'dow=' || (dayofweek(o_orderdate) + 1)]) AS name FROM orders")
_scale("words", "benchmark", "item_id", lambda: z.words(F.col("text"), "[a-zà-ÿ]+"), "SELECT item_id AS obj, unnest(regexp_extract_all(lower(text), '[a-zà-ÿ]+')) AS name FROM benchmark")
_scale("json_values", "events", "event_id", lambda: z.json_values(F.col("props"), "$.k", "k"), "SELECT event_id AS obj, 'k=' || regexp_extract(props, '\"k\": *([0-9]+)', 1) AS name FROM events")
_scale("json_keys", "events", "event_id", lambda: z.json_keys(F.col("props")), "SELECT event_id AS obj, unnest(regexp_extract_all(props, '\"([a-z]+)\":', 1)) AS name FROM events")
_scale("vector", "embeddings", "vec_id", lambda: z.vector_scale(F.col("embedding"), 20, 0.1), "SELECT vec_id AS obj, CAST(k AS VARCHAR) AS name FROM embeddings, range(1, 21) r(k) WHERE embedding[k] > 0.1")
_scale("markup", "pages", "page_id", lambda: z.regex_set(F.col("html"), "<([a-z][a-z0-9]*)"), "SELECT page_id AS obj, unnest(regexp_extract_all(html, '<([a-z][a-z0-9]*)', 1)) AS name FROM pages")
_scale("map", "part", "p_partkey", lambda: z.map_scale(F.map_from_arrays(F.array(F.lit("brand"), F.lit("size")), F.array(F.col("p_brand"), F.col("p_size").cast("string")))), "SELECT p_partkey AS obj, unnest(['brand=' || p_brand, 'size=' || p_size]) AS name FROM part")
_scale("money", "supplier", "s_suppkey", lambda: z.money(F.col("s_acctbal"), "bal"), "SELECT s_suppkey AS obj, 'bal=' || CAST(CAST(s_acctbal AS DECIMAL(18, 2)) AS VARCHAR) AS name FROM supplier")


def _null_as(spark, sf_dir: str, *_):
    joined = _read(spark, sf_dir, "documents").join(_read(spark, sf_dir, "labels"), "doc_id", "left")
    return joined.select(F.col("doc_id").alias("obj"), F.explode(z.nominal(F.col("quality"), "q", "none")).alias("name"))


QUERIES["scale_null_as"] = (_null_as, "SELECT d.doc_id AS obj, 'q=' || coalesce(CAST(quality AS VARCHAR), 'none') AS name FROM documents d LEFT JOIN labels l ON l.doc_id = d.doc_id")
QUERIES["scale_related"] = (
    lambda spark, sf_dir, *_: (lambda c, o: z.related(c, o, c["c_custkey"] == o["o_custkey"], z.nominal(F.col("o_orderstatus"), "st"), "c_custkey", ("st=none",)).select("obj", F.explode("attrs").alias("name")))(_read(spark, sf_dir, "customer"), _read(spark, sf_dir, "orders")),
    "SELECT DISTINCT c_custkey AS obj, 'st=' || coalesce(o_orderstatus, 'none') AS name FROM customer LEFT JOIN orders ON o_custkey = c_custkey",
)

# Groupings, windows and set predicates on families.

_BANDED = "SELECT CASE WHEN support < 10 THEN 'rare' ELSE 'often' END AS band, size FROM con"


def _banded(mined, spark, sf_dir: str) -> DataFrame:
    return mined(spark, sf_dir, "document_meta").strings().select(F.when(F.col("support") < 10, "rare").otherwise("often").alias("band"), "size")


def _shown(df: DataFrame) -> DataFrame:
    """Subtotals are named: all for bands, -1 for sizes."""
    return df.select(F.coalesce("band", F.lit("all")).alias("band"), F.coalesce("size", F.lit(-1)).alias("size"), "n")


for _name, _grouped, _by in (
    ("cube", lambda spark, t: t.cube("band", "size").agg(F.count("*").alias("n")), "CUBE (band, size)"),
    ("rollup", lambda spark, t: t.rollup("band", "size").agg(F.count("*").alias("n")), "ROLLUP (band, size)"),
    ("grouping_sets", lambda spark, t: spark.sql("SELECT band, size, count(*) AS n FROM {t} GROUP BY GROUPING SETS ((band), (size), ())", t=t), "GROUPING SETS ((band), (size), ())"),
):
    QUERIES[f"sizes_{_name}"] = (
        lambda spark, sf_dir, context, mined, g=_grouped: _shown(g(spark, _banded(mined, spark, sf_dir))),
        oracle.concepts("document_meta", f"SELECT coalesce(band, 'all') AS band, coalesce(size, -1) AS size, n FROM (SELECT band, size, count(*) AS n FROM ({_BANDED}) GROUP BY {_by})"),
    )


def _ranks(spark, sf_dir, context, mined):
    own = Window.partitionBy("size")
    places = mined(spark, sf_dir, "session_mix").strings().select("intent", "size", F.row_number().over(own.orderBy(F.desc("support"), "intent")).alias("place"), F.dense_rank().over(own.orderBy(F.desc("support"))).alias("level"))
    return places.where("place <= 5")


QUERIES["ranks_within_size"] = (
    _ranks,
    oracle.concepts("session_mix", "SELECT intent, size, CAST(row_number() OVER (PARTITION BY size ORDER BY support DESC, intent) AS INT) AS place, CAST(dense_rank() OVER (PARTITION BY size ORDER BY support DESC) AS INT) AS level FROM con QUALIFY place <= 5"),
)


def _overlapping(spark, sf_dir, context, mined):
    r = mined(spark, sf_dir, "nation_activity")
    ctx = r.context
    a, b = (r.concepts.select(*[F.col(w).alias(f"{p}{i}") for i, w in enumerate(ctx.words)]) for p in "ab")
    pairs = a.crossJoin(b).where(bits.lectic_less(ctx.columns("a"), ctx.columns("b")))
    shared = bits.overlap(ctx.columns("a"), ctx.columns("b"))
    name = lambda p: bits.intent_string(ctx.columns(p), ctx.attributes)
    return pairs.select(name("a").alias("a"), name("b").alias("b"), shared.alias("shared"), bits.contains(ctx.columns("b"), ctx.columns("a")).alias("inside"), bits.disjoint(ctx.columns("a"), ctx.columns("b")).alias("apart"))


QUERIES["set_predicates_nation_activity"] = (_overlapping, oracle.concepts("nation_activity", "SELECT a.intent AS a, b.intent AS b, CAST(bit_count(a.w & b.w) AS INT) AS shared, (b.w & a.w) = a.w AS inside, (a.w & b.w) = 0 AS apart FROM con a JOIN con b ON a.w < b.w"))
QUERIES["intents_with_must_have"] = (
    lambda spark, sf_dir, context, mined: (lambda r: r.concepts.where(F.array_contains(bits.intent_array(r.context.columns(), r.context.attributes), "flag=R")).select(r.context.string().alias("intent"), "support"))(mined(spark, sf_dir, "lineitem_profile")),
    oracle.concepts("lineitem_profile", "SELECT intent, support FROM con WHERE list_contains(string_split(intent, ','), 'flag=R')"),
)
QUERIES["registry_probe"] = (
    lambda spark, sf_dir, context, mined: (lambda r: r.concepts.select(bits.head_of(r.context.columns(), r.context.m).alias("head"), bits.size_of(r.context.columns()).alias("size")).groupBy("head", "size").agg(F.count("*").alias("intents")))(mined(spark, sf_dir, "session_keys")),
    oracle.concepts("session_keys", "SELECT head, size, count(*) AS intents FROM (SELECT c.w, c.size, coalesce(min(a.rank), (SELECT CAST(count(*) AS INT) FROM attr)) AS head FROM con c LEFT JOIN attr a ON ((c.w >> (125 - a.rank)) & 1) = 1 GROUP BY c.w, c.size) GROUP BY head, size"),
)

# Joins by time and range.


def _gap_sessions(spark, sf_dir, *_):
    own = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = _read(spark, sf_dir, "events").withColumn("gap", F.coalesce((F.col("ts") - F.lag("ts").over(own)) > F.expr("INTERVAL '12' HOUR"), F.lit(True)))
    e = e.withColumn("session", F.sum(F.col("gap").cast("int")).over(own))
    return e.groupBy("user_id", "session").agg(F.array_join(F.array_sort(F.collect_set("event_type")), ",").alias("types"), F.count("*").alias("n"))


QUERIES["session_gap_objects"] = (
    _gap_sessions,
    "SELECT user_id, CAST(session AS BIGINT) AS session, string_agg(DISTINCT event_type, ',' ORDER BY event_type) AS types, count(*) AS n FROM (SELECT *, sum(g) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS session FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) > INTERVAL 12 HOUR OR lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) IS NULL THEN 1 ELSE 0 END AS g FROM events)) GROUP BY user_id, session",
)


def _as_of(spark, sf_dir, *_):
    """Every purchase with the latest earlier view of its user: one sort, no range join."""
    own = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    e = _read(spark, sf_dir, "events")
    seen = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(own)
    return e.withColumn("view_id", seen).where("event_type = 'purchase'").select("event_id", "user_id", F.coalesce("view_id", F.lit(-1)).alias("view_id"))


QUERIES["asof_purchase_view"] = (
    _as_of,
    "SELECT event_id, user_id, coalesce(view_id, -1) AS view_id FROM (SELECT *, last_value(CASE WHEN event_type = 'view' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS view_id FROM events) WHERE event_type = 'purchase'",
)


def _band_join(spark, sf_dir, *_):
    """Parts and suppliers of nearly equal amounts, by buckets one band wide and their neighbours."""
    p = _read(spark, sf_dir, "part").select("p_partkey", "p_retailprice", F.explode(F.array(*[F.floor(F.col("p_retailprice") / 2) + k for k in (-1, 0, 1)])).alias("bucket"))
    s = _read(spark, sf_dir, "supplier").select("s_suppkey", "s_acctbal", F.floor(F.col("s_acctbal") / 2).alias("bucket"))
    return p.join(s, "bucket").where(F.abs(F.col("p_retailprice") - F.col("s_acctbal")) <= 2).select("p_partkey", "s_suppkey")


QUERIES["band_join_part_supplier"] = (_band_join, "SELECT p_partkey, s_suppkey FROM part JOIN supplier ON abs(p_retailprice - s_acctbal) <= 2")

# SQL functions, an aggregate and a table function.


def _feasible(spark, sf_dir, context, mined):
    sqlapi.register(spark)
    ctx = context(spark, sf_dir, "tiny")
    ranks = spark.range(ctx.m).select(F.col("id").cast("int").alias("p"))
    return spark.sql("SELECT a.obj AS a, b.obj AS b, p, lectic_less(a.w0, b.w0) AS less, seed_of(a.w0, p) AS seed FROM {o} a JOIN {o} b ON a.obj <> b.obj JOIN {r} ON lectic_less_at(a.w0, b.w0, p)", o=ctx.objects, r=ranks)


QUERIES["sql_fn_feasible"] = (
    _feasible,
    oracle.over_rows("tiny", ", o AS (SELECT obj, CAST(w >> 63 AS BIGINT) AS w0 FROM pk), pp AS (SELECT a.obj AS a, b.obj AS b, a.w0 AS x, b.w0 AS y, CAST(floor(log2(xor(a.w0, b.w0))) AS INT) AS k FROM o a JOIN o b ON a.obj <> b.obj WHERE a.w0 < b.w0) SELECT a, b, 62 - k AS p, TRUE AS less, ((x >> (k + 1)) << (k + 1)) | (CAST(1 AS BIGINT) << k) AS seed FROM pp"),
)
QUERIES["udaf_intersect"] = (
    lambda spark, sf_dir, *_: _read(spark, sf_dir, "orders").join(_read(spark, sf_dir, "customer"), F.col("o_custkey") == F.col("c_custkey")).select("c_nationkey", F.concat(z.nominal(F.col("o_orderstatus"), "st"), z.nominal(F.year("o_orderdate"), "year"), z.nominal(F.col("c_mktsegment"), "seg")).alias("attrs"), "o_custkey").groupBy("o_custkey").agg(sqlapi.intersect_agg("attrs").alias("shared")).select("o_custkey", F.array_join("shared", ",").alias("shared")),
    "WITH a AS (SELECT o_orderkey, o_custkey, unnest(['st=' || o_orderstatus, 'year=' || year(o_orderdate), 'seg=' || c_mktsegment]) AS name FROM orders JOIN customer ON o_custkey = c_custkey), n AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey), s AS (SELECT o_custkey, name FROM a JOIN n USING (o_custkey) GROUP BY o_custkey, name, n HAVING count(*) = n) SELECT n.o_custkey, coalesce(string_agg(name, ',' ORDER BY name), '') AS shared FROM n LEFT JOIN s ON s.o_custkey = n.o_custkey GROUP BY n.o_custkey",
)


def _by_group(spark, sf_dir, *_):
    return _each_day(spark, WORKLOADS["session_mix"].profiles(spark, sf_dir).withColumn("day", F.right("obj", F.lit(10))))


def _each_day(spark, rows: DataFrame) -> DataFrame:
    """The table function on each day's sessions."""
    sqlapi.register(spark)
    return spark.sql("SELECT * FROM mine_concepts_by_day(TABLE(SELECT day, attrs FROM {rows}) PARTITION BY day)", rows=rows)


_DAYS_SQL = f"""WITH RECURSIVE {oracle.packed(WORKLOADS['session_mix'])},
daily AS MATERIALIZED (SELECT right(obj, 10) AS day, w, count(*) AS n FROM pk GROUP BY ALL),
found(day, w) AS (SELECT day, bit_or(w) FROM daily GROUP BY day UNION SELECT f.day, f.w & d.w FROM found f JOIN daily d ON d.day = f.day),
held AS (SELECT f.day, f.w, CAST(coalesce(sum(d.n), 0) AS BIGINT) AS support FROM found f LEFT JOIN daily d ON d.day = f.day AND (d.w & f.w) = f.w GROUP BY f.day, f.w)
SELECT h.day, n.intent, n.size, h.support FROM held h JOIN ({oracle.named('found')}) n ON n.w = h.w"""
QUERIES["udtf_concepts_by_day"] = (_by_group, _DAYS_SQL)


def _views(spark, sf_dir, context, mined):
    r = mined(spark, sf_dir, "lineitem_profile")
    files.publish(r.context, r.concepts, "galoislake_")
    return spark.sql("SELECT size, max(support) AS best, count_if(array_contains(names, 'year=1995')) AS in_1995 FROM galoislake_concepts GROUP BY size")


QUERIES["sql_views_lineitem_profile"] = (_views, oracle.concepts("lineitem_profile", "SELECT size, max(support) AS best, count(*) FILTER (WHERE list_contains(string_split(intent, ','), 'year=1995')) AS in_1995 FROM con GROUP BY size"))

for _kind in ("parquet", "orc", "json", "csv", "baskets"):
    QUERIES[f"roundtrip_{_kind}"] = (
        lambda spark, sf_dir, context, mined, k=_kind: files.roundtrip(WORKLOADS["document_terms"].profiles(spark, sf_dir), new_path(spark, k), k).select("obj", F.array_join(F.array_sort("attrs"), ",").alias("names")),
        "SELECT CAST(d.doc_id AS VARCHAR) AS obj, coalesce(string_agg(DISTINCT i.name, ',' ORDER BY i.name), '') AS names FROM documents d LEFT JOIN (" + WORKLOADS["document_terms"].incidence + ") i ON i.obj = d.doc_id GROUP BY d.doc_id",
    )


def _cross_file(spark, sf_dir, context, mined):
    path = new_path(spark, "cross")
    files.write_cross_table(context(spark, sf_dir, "tiny"), path)
    return files.read_cross_table(spark, path).select(F.col("obj").cast("int").alias("obj"), F.array_join("attrs", "").alias("names"))


QUERIES["roundtrip_cross_table"] = (_cross_file, oracle.over_rows("tiny", "SELECT obj, string_agg(name, '' ORDER BY name) AS names FROM inc GROUP BY obj"))


def _concept_files(spark, sf_dir, context, mined):
    path = new_path(spark, "concepts")
    r = mined(spark, sf_dir, "session_mix")
    files.write_concepts(r.concepts, path)
    return spark.read.parquet(path).select(r.context.string().alias("intent"), "support")


QUERIES["roundtrip_concepts"] = (_concept_files, oracle.concepts("session_mix", "SELECT intent, support FROM con"))
