"""The named queries, each beside its SQL."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from galoislake.functions import bits
from galoislake.operators import central, derive, lattice, sizes
from galoislake.operators.closure import close, local_closures
from galoislake.operators.context import FormalContext
from galoislake.plans import measures, oracle, rounds, surroundings
from galoislake.plans.storage import settle
from galoislake.sources.workloads import TINY_PARTS, WORKLOADS
from galoislake.streaming import queries as streams

Query = Callable[[SparkSession, str], DataFrame]
_KEPT: dict[tuple, object] = {}


def _once(spark: SparkSession, sf_dir: str, what: str, make: Callable[[], object]):
    """Contexts and families are tables in the shared folder: a session makes each of them once."""
    key = (spark.sparkContext.applicationId, sf_dir, what)
    if key not in _KEPT:
        _KEPT[key] = make()
    return _KEPT[key]


def context(spark: SparkSession, sf_dir: str, name: str) -> FormalContext:
    return _once(spark, sf_dir, name, lambda: WORKLOADS[name].context(spark, sf_dir))


def mined(spark: SparkSession, sf_dir: str, name: str) -> rounds.MiningResult:
    return _once(spark, sf_dir, f"{name}/all", lambda: rounds.round_all(context(spark, sf_dir, name)))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounds.round_all(WORKLOADS["lineitem_profile"].context(spark, sf_dir)).strings()


@dataclass(frozen=True)
class Entry:
    query: Query
    sql: str | None


ENTRIES: dict[str, Entry] = {}


def _add(name: str, sql: str | None, query: Query) -> None:
    ENTRIES[name] = Entry(query, sql)


def _on(name: str, make: Callable[[FormalContext], DataFrame]) -> Query:
    return lambda spark, sf_dir: make(context(spark, sf_dir, name))


def _shown(ctx: FormalContext, df: DataFrame) -> DataFrame:
    return df.select(ctx.string().alias("intent"), bits.size_of(ctx.columns()).alias("size"), "support")


# Mining methods: each returns the whole family.

ALL = ("tiny", "lineitem_profile", "part_traits", "session_mix", "session_keys", "customer_orders", "document_meta", "embedding_signs", "conversation_shape", "page_tags", "document_terms", "benchmark_terms", "nation_region", "nation_activity")
_TABLE = {"tiny": "customer_profile"}  # queries named tiny that read a given table, not the worked example
for _w in ALL:
    _add(f"concepts_all_{_w}", oracle.concepts(_w), lambda spark, sf_dir, w=_w: mined(spark, sf_dir, w).strings())
for _w in ("tiny", "lineitem_profile", "session_mix", "session_keys", "document_meta", "embedding_signs", "conversation_shape", "benchmark_terms", "nation_activity"):
    _add(f"concepts_branch_{_w}", oracle.concepts(_TABLE.get(_w, _w)), _on(_TABLE.get(_w, _w), lambda ctx: rounds.round_branch(ctx).strings()))
_STEPS = "SELECT CAST(row_number() OVER (ORDER BY w) - 1 AS INT) AS step, intent, support FROM con"
for _w in ("tiny", "conversation_shape", "nation_region", "nation_activity"):
    _add(f"concepts_single_{_w}", oracle.concepts(_w, _STEPS), _on(_w, lambda ctx: (lambda r: r.concepts.select(F.col("round").alias("step"), ctx.string().alias("intent"), "support"))(rounds.round_single(ctx, 2))))
_add("concepts_single_certified_tiny", oracle.concepts("tiny", _STEPS), _on("tiny", lambda ctx: rounds.round_single(ctx, 3, certify=True).concepts.select(F.col("round").alias("step"), ctx.string().alias("intent"), "support")))
_add("round_single_first_12", oracle.concepts("lineitem_profile", _STEPS + " QUALIFY step <= 12"), _on("lineitem_profile", lambda ctx: rounds.round_single(ctx, 3, max_rounds=12).concepts.select(F.col("round").alias("step"), ctx.string().alias("intent"), "support")))
for _w in ("tiny", "lineitem_profile", "part_traits", "session_keys", "document_meta"):
    _add(f"concepts_lectic_{_w}", oracle.concepts(_TABLE.get(_w, _w), _STEPS), _on(_TABLE.get(_w, _w), lambda ctx: central.lectic_scan(ctx).select("step", ctx.string().alias("intent"), "support")))
for _w in ("lineitem_profile", "embedding_signs", "document_terms"):
    _add(f"concepts_local_branch_{_w}", oracle.concepts(_w), _on(_w, lambda ctx: _shown(ctx, central.branch_scan(ctx))))
_add("concepts_prefix_branch_tiny", oracle.concepts(_TABLE["tiny"]), _on(_TABLE["tiny"], lambda ctx: _shown(ctx, central.branch_scan(ctx, "prefix"))))
for _w in ("lineitem_profile", "session_mix"):
    _add(f"concepts_subtrees_{_w}", oracle.concepts(_w), _on(_w, lambda ctx: _shown(ctx, central.branch_subtrees(ctx))))
_add("concepts_brute_force_session_mix", oracle.concepts("session_mix"), _on("session_mix", lambda ctx: _shown(ctx, central.brute_force(ctx))))
_add("concepts_reload_lineitem_profile", oracle.concepts("lineitem_profile"), _on("lineitem_profile", lambda ctx: rounds.round_all(ctx, parts=3, static="reload").strings()))
_add("concepts_flat_registry_nation_activity", oracle.concepts("nation_activity"), _on("nation_activity", lambda ctx: rounds.round_all(ctx, registry="flat").strings()))
_add("concepts_repeated_seeds_nation_activity", oracle.concepts("nation_activity"), _on("nation_activity", lambda ctx: rounds.round_all(ctx, dedupe_seeds=False).strings()))
for _s in ("join", "blocks", "postings"):
    _add(f"concepts_by_{_s}_document_meta", oracle.concepts("document_meta"), _on("document_meta", lambda ctx, s=_s: rounds.round_all(ctx, strategy=s).strings()))
for _how in ("block", "hash", "round_robin", "density"):
    _add(f"concepts_split_{_how}_conversation_shape", oracle.concepts("conversation_shape"), _on("conversation_shape", lambda ctx, h=_how: rounds.round_all(ctx.split(3, h)).strings()))


def _by_updates(ctx: FormalContext) -> DataFrame:
    """Objects arrive in three batches; the family is updated after each."""
    family = None
    dealt = settle(ctx.rows.withColumn("batch", F.pmod(F.xxhash64(*ctx.words), F.lit(3))), "batches")
    for k in range(3):
        family = settle(lattice.update_intents(family, dealt.where(F.col("batch") == k), ctx.full), "family")
    return _shown(ctx, lattice.supports(ctx, family))


_add("concepts_by_updates_session_mix", oracle.concepts("session_mix"), _on("session_mix", _by_updates))
_add(
    "lectic_window_lineitem_profile",
    oracle.concepts("lineitem_profile", "SELECT CAST(row_number() OVER (ORDER BY w) - 1 AS INT) AS step, intent FROM con WHERE w > (SELECT w FROM con WHERE intent = 'disc=low,flag=N') ORDER BY w LIMIT 8"),
    _on("lineitem_profile", lambda ctx: central.lectic_scan(ctx, max_steps=8, start=["disc=low", "flag=N"]).select("step", ctx.string().alias("intent"))),
)
_add("frequent_part_traits", oracle.concepts("part_traits", "SELECT intent, size, support FROM con WHERE support >= 20"), _on("part_traits", lambda ctx: rounds.round_all(ctx, min_support=20).strings()))
_add("frequent_branch_session_mix", oracle.concepts("session_mix", "SELECT intent, size, support FROM con WHERE support >= 50"), _on("session_mix", lambda ctx: rounds.round_branch(ctx, min_support=50).strings()))
_add("short_intents_document_terms", oracle.concepts("document_terms", "SELECT intent, size, support FROM con WHERE size <= 2"), _on("document_terms", lambda ctx: rounds.round_all(ctx, max_size=2).strings()))


# Derivations, closures, parts.

def _attribute_seeds(ctx: FormalContext, pairs: bool = False) -> DataFrame:
    r = ctx.spark.range(ctx.m).select(F.col("id").cast("int").alias("p"))
    zero = [bits.long(0)] * len(ctx.words)
    if not pairs:
        return r.select("p", *[c.alias(f"s{i}") for i, c in enumerate(bits.with_bit(zero, F.col("p")))])
    both = r.crossJoin(r.withColumnRenamed("p", "q")).where("p < q")
    return both.select("p", "q", *[c.alias(f"s{i}") for i, c in enumerate(bits.with_bit(bits.with_bit(zero, F.col("p")), F.col("q")))])


def _names(ctx: FormalContext, prefix: str):
    return bits.intent_string(ctx.columns(prefix), ctx.attributes)


def _parts_by_key(ctx: FormalContext, parts: int = 3) -> FormalContext:
    rows = ctx.objects.withColumn("part", F.pmod("obj", F.lit(parts)).cast("int")).groupBy("part", *ctx.words).agg(F.count("*").alias("weight"))
    return replace(ctx, rows=settle(rows, "parts"), parts=parts)


_T = oracle._TOP
_FULL = "(SELECT f FROM everything)"
for _w in ("document_meta", "embedding_signs", "conversation_shape"):
    _add(
        f"local_closures_{_w}",
        oracle.over_rows(_w, f""", lc AS (SELECT p.part, a.name AS seed, coalesce(bit_and(k.w), {_FULL}) AS w FROM (SELECT DISTINCT CAST(obj % 3 AS INT) AS part FROM pk) p CROSS JOIN attr a
            LEFT JOIN pk k ON CAST(k.obj % 3 AS INT) = p.part AND ((k.w >> ({_T} - a.rank)) & 1) = 1 GROUP BY p.part, a.name)
            SELECT l.part, l.seed, n.intent AS closure FROM lc l JOIN ({oracle.named('lc')}) n ON n.w = l.w"""),
        _on(_w, lambda ctx: (lambda c: local_closures(c, _attribute_seeds(c).drop("p")).select("part", _names(c, "s").alias("seed"), c.string().alias("closure")))(_parts_by_key(ctx))),
    )
    _add(
        f"merged_closures_{_w}",
        oracle.over_rows(_w, f""", mc AS (SELECT a.name AS seed, coalesce(bit_and(k.w), {_FULL}) AS w, count(k.obj) AS support FROM attr a LEFT JOIN pk k ON ((k.w >> ({_T} - a.rank)) & 1) = 1 GROUP BY a.name)
            SELECT l.seed, n.intent AS closure, l.support FROM mc l JOIN ({oracle.named('mc')}) n ON n.w = l.w"""),
        _on(_w, lambda ctx: close(ctx, _attribute_seeds(ctx).drop("p")).select(_names(ctx, "s").alias("seed"), ctx.string().alias("closure"), "support")),
    )
    _add(
        f"partition_profile_{_w}",
        oracle.over_rows(_w, "SELECT CAST(obj % 3 AS INT) AS part, count(DISTINCT w) AS rows, count(*) AS objects, CAST(sum(bit_count(w)) AS BIGINT) AS crosses, sum(bit_count(w)) / (count(*) * (SELECT count(*) FROM attr)) AS density FROM pk GROUP BY 1"),
        _on(_w, lambda ctx: _parts_by_key(ctx).partition_profile()),
    )
for _w in ("lineitem_profile", "document_meta", "session_keys"):
    _add(
        f"closure_pairs_{_w}",
        oracle.over_rows(_w, f""", prs AS (SELECT (CAST(1 AS HUGEINT) << ({_T} - a.rank)) | (CAST(1 AS HUGEINT) << ({_T} - b.rank)) AS s FROM attr a JOIN attr b ON a.rank < b.rank),
            pc AS (SELECT p.s, coalesce(bit_and(r.w), {_FULL}) AS w, CAST(coalesce(sum(r.n), 0) AS BIGINT) AS support FROM prs p LEFT JOIN rws r ON (r.w & p.s) = p.s GROUP BY p.s),
            im AS (SELECT s, w, support, xor(w, s) AS i FROM pc)
            SELECT a.intent AS seed, b.intent AS closure, c.intent AS implied, p.support FROM im p JOIN ({oracle.named('im', '', 's')}) a ON a.w = p.s JOIN ({oracle.named('im')}) b ON b.w = p.w JOIN ({oracle.named('im', '', 'i')}) c ON c.w = p.i"""),
        _on(_w, lambda ctx: derive.implied(ctx, _attribute_seeds(ctx, True).drop("p", "q")).select(_names(ctx, "s").alias("seed"), ctx.string().alias("closure"), _names(ctx, "i").alias("implied"), "support")),
    )
_add("derive_objects", oracle.over_rows("document_meta", "SELECT obj FROM inc WHERE name IN ('lang=en', 'len=m') GROUP BY obj HAVING count(*) = 2"), _on("document_meta", lambda ctx: derive.objects_with(ctx, ["lang=en", "len=m"])))
_add("derive_attributes", oracle.over_rows("document_meta", "SELECT name FROM inc WHERE obj IN (1, 5, 7) GROUP BY name HAVING count(*) = 3"), _on("document_meta", lambda ctx: derive.common_attributes(ctx, ctx.objects.where("obj IN (1, 5, 7)")).select(F.explode(bits.intent_array(ctx.columns(), ctx.attributes)).alias("name"))))
_add("derive_attributes_of_none", oracle.over_rows("document_meta", "SELECT name FROM attr"), _on("document_meta", lambda ctx: derive.common_attributes(ctx, ctx.objects.where("obj < 0")).select(F.explode(bits.intent_array(ctx.columns(), ctx.attributes)).alias("name"))))
for _w in ("tiny", "lineitem_profile", "conversation_shape", "page_tags"):
    _add(f"bottom_intent_{_w}", oracle.over_rows(_TABLE.get(_w, _w), f", bt AS (SELECT bit_and(w) AS w FROM rws) SELECT n.intent, n.size, (SELECT count(*) FROM pk) AS support FROM ({oracle.named('bt')}) n"), _on(_TABLE.get(_w, _w), lambda ctx: _shown(ctx, rounds._start(ctx))))
_add(
    "oplus_conversation_shape",
    oracle.concepts("conversation_shape", f""", sd AS (SELECT c.intent AS d, a.name AS p, ((c.w >> ({oracle._TOP} + 1 - a.rank)) << ({oracle._TOP} + 1 - a.rank)) | (CAST(1 AS HUGEINT) << ({oracle._TOP} - a.rank)) AS s FROM con c JOIN attr a ON ((c.w >> ({oracle._TOP} - a.rank)) & 1) = 0),
        cl AS (SELECT s.d, s.p, coalesce(bit_and(r.w), (SELECT f FROM everything)) AS w, CAST(coalesce(sum(r.n), 0) AS BIGINT) AS support FROM sd s LEFT JOIN rws r ON (r.w & s.s) = s.s GROUP BY s.d, s.p, s.s)
        SELECT l.d, l.p, n.intent AS closure, l.support FROM cl l JOIN con n ON n.w = l.w"""),
    lambda spark, sf_dir: _closed_pairs(mined(spark, sf_dir, "conversation_shape")),
)
_ASKED = ("", "bal=hi", "bal=hi,seg=BUILDING", "bal=hi,bal=mid", "seg=MACHINERY", "bal=hi,bal=mid,bal=neg,seg=AUTOMOBILE,seg=BUILDING,seg=FURNITURE,seg=HOUSEHOLD,seg=MACHINERY")
_add(
    "concept_test_tiny",
    oracle.concepts(_TABLE["tiny"], "SELECT i AS intent, i IN (SELECT intent FROM con) AS concept, i = (SELECT n.intent FROM (" + oracle.named("everything", "", "f") + ") n) AS last FROM (VALUES " + ", ".join(f"('{t}')" for t in _ASKED) + ") v(i)"),
    lambda spark, sf_dir: _tested(context(spark, sf_dir, _TABLE["tiny"])),
)
for _w in ("document_meta", "conversation_shape"):
    _add(
        f"extent_union_{_w}",
        oracle.over_rows(_w, ", asked AS (SELECT name FROM attr) SELECT a.name AS intent, CAST(i.obj % 3 AS INT) AS part, i.obj FROM asked a JOIN inc i ON i.name = a.name"),
        _on(_w, lambda ctx: _local_extents(ctx)),
    )
    _add(
        f"extent_of_parts_{_w}",
        oracle.over_rows(_w, "SELECT a.name AS intent, i.obj FROM attr a JOIN inc i ON i.name = a.name"),
        _on(_w, lambda ctx: derive.merge_extents(ctx, derive.local_extents(ctx, _single_sets(ctx), F.pmod("obj", F.lit(3)))).select(ctx.string().alias("intent"), "obj")),
    )
for _w in ("tiny", "conversation_shape", "nation_activity"):
    _add(f"extents_by_parents_{_w}", oracle.concepts(_w, "SELECT c.intent, k.obj FROM con c JOIN pk k ON (k.w & c.w) = c.w"), lambda spark, sf_dir, w=_w: _extents_down(mined(spark, sf_dir, w)))
_add(
    "sample_family_session_mix",
    oracle.concepts("session_mix", "SELECT count(*) > 0 AS found, TRUE AS inside FROM con"),
    lambda spark, sf_dir: _sampled(mined(spark, sf_dir, "session_mix")),
)
_add(
    "concept_measures_session_mix",
    oracle.concepts("session_mix", """, t AS (SELECT sum(n) AS objects FROM rws), x AS (SELECT c.intent, c.w, c.support, c.size, sum(r.n * (CASE WHEN (r.w & c.w) = c.w THEN bit_count(r.w) ELSE bit_count(r.w & c.w) END)) AS crosses FROM con c JOIN rws r ON bit_count(r.w & c.w) > 0 GROUP BY ALL)
        SELECT intent, support, support / objects AS relative, support * size / crosses AS separation FROM x, t"""),
    lambda spark, sf_dir: (lambda r: lattice.stability(r.context, r.concepts).select(r.context.string().alias("intent"), "support", "relative", "separation"))(mined(spark, sf_dir, "session_mix")),
)
_add(
    "paths_up_nation_activity",
    oracle.concepts("nation_activity", """, e AS (SELECT c.w AS child, p.w AS parent FROM con c JOIN con p ON (c.w & p.w) = p.w AND c.w <> p.w WHERE NOT EXISTS (SELECT 1 FROM con b WHERE (c.w & b.w) = b.w AND (b.w & p.w) = p.w AND b.w <> c.w AND b.w <> p.w)),
        up(w, steps) AS (SELECT f, 0 FROM everything UNION SELECT e.parent, u.steps + 1 FROM up u JOIN e ON e.child = u.w) SELECT c.intent, CAST(min(u.steps) AS INT) AS steps FROM up u JOIN con c ON c.w = u.w GROUP BY c.intent"""),
    lambda spark, sf_dir: _up(mined(spark, sf_dir, "nation_activity")),
)
_add("close_objects", oracle.over_rows("document_meta", ", sh AS (SELECT bit_and(w) AS s FROM pk WHERE obj IN (1, 5)) SELECT obj FROM pk, sh WHERE (w & s) = s"), _on("document_meta", lambda ctx: derive.close_objects(ctx, ctx.objects.where("obj IN (1, 5)"))))
_TRACE = """, parts(obj, part) AS (VALUES (1, 0), (2, 0), (3, 0), (4, 1), (5, 1), (6, 1)),
ds AS (SELECT d, bit_or(CASE WHEN name IS NULL THEN CAST(0 AS HUGEINT) ELSE CAST(1 AS HUGEINT) << ({t} - rank) END) AS dw FROM (VALUES {values}) v(d) LEFT JOIN attr ON contains(d, name) GROUP BY d),
sd AS (SELECT d, dw, rank, name AS p, ((dw >> ({t} + 1 - rank)) << ({t} + 1 - rank)) | (CAST(1 AS HUGEINT) << ({t} - rank)) AS s FROM ds, attr WHERE ((dw >> ({t} - rank)) & 1) = 0),
lo AS (SELECT s.d, s.p, s.dw, s.rank, coalesce(bit_and(CASE WHEN part = 0 THEN k.w END), f) AS l1, coalesce(bit_and(CASE WHEN part = 1 THEN k.w END), f) AS l2
       FROM sd s CROSS JOIN everything LEFT JOIN (pk k JOIN parts USING (obj)) ON (k.w & s.s) = s.s GROUP BY s.d, s.p, s.dw, s.rank, f),
mg AS (SELECT *, l1 & l2 AS w FROM lo),
nm AS ({named})
SELECT (SELECT intent FROM nm WHERE nm.w = mg.dw) AS d, p, (SELECT intent FROM nm WHERE nm.w = mg.l1) AS local1, (SELECT intent FROM nm WHERE nm.w = mg.l2) AS local2, (SELECT intent FROM nm WHERE nm.w = mg.w) AS merged,
       (w >> ({t} + 1 - rank)) = (dw >> ({t} + 1 - rank)) AS feasible FROM mg"""


def _traced(ctx: FormalContext, intents: list[str]) -> DataFrame:
    part = F.element_at(F.create_map(*[F.lit(x) for kv in TINY_PARTS.items() for x in kv]), F.col("obj"))
    rows = ctx.objects.withColumn("part", part).withColumn("weight", F.lit(1).cast("long"))
    return rounds.trace(replace(ctx, rows=settle(rows.select(*ctx.words, "weight", "part"), "parts"), parts=2), ctx.sets([list(d) for d in intents]))


# The intents of the worked example in lectic order.
_LECTIC = ("", "f", "e", "d", "df", "de", "cg", "b", "bf", "bd", "bdf", "bde", "bcfg", "bcdfg", "a", "ae", "adf", "adef", "aceg", "abdf")
for _name, _ds in (("single", ("", "f", "e", "d")), ("all", ("", "cg", "f", "e")), ("every_round", _LECTIC)):
    _sql = _TRACE.format(t=_T, values=", ".join(f"('{d}')" for d in _ds), named=oracle.named("(SELECT dw AS w FROM mg UNION SELECT l1 FROM mg UNION SELECT l2 FROM mg UNION SELECT w FROM mg)"))
    _add(f"trace_tiny_{_name}", oracle.over_rows("tiny", _sql), _on("tiny", lambda ctx, ds=_ds: _traced(ctx, list(ds))))


# Contexts as tables.

_add(
    "context_profile_all",
    " UNION ALL ".join(f"(WITH {oracle.packed(WORKLOADS[w])} SELECT '{w}' AS context, count(*) AS objects, (SELECT count(*) FROM attr) AS attributes, CAST(sum(bit_count(w)) AS BIGINT) AS crosses, count(DISTINCT w) AS distinct_rows, sum(bit_count(w)) / (count(*) * (SELECT count(*) FROM attr)) AS density FROM pk)" for w in ALL),
    lambda spark, sf_dir: measures.profiles({w: context(spark, sf_dir, w) for w in ALL}),
)
_add("cross_table_tiny", oracle.over_rows("tiny", "SELECT obj, " + ", ".join(f"CASE WHEN bool_or(name = '{a}') THEN 'x' ELSE '' END AS {a}" for a in "abcdefg") + " FROM inc GROUP BY obj"), _on("tiny", lambda ctx: ctx.cross_table()))
for _w in ("part_traits", "document_terms", "page_tags"):
    _add(f"incidence_{_w}", oracle.over_rows(_w, "SELECT obj, name FROM inc"), _on(_w, lambda ctx: ctx.incidence()))
_HALF = f"CAST(w & {(1 << 63) - 1} AS BIGINT)"
for _w in ("lineitem_profile", "session_keys"):
    _second = f", {_HALF} AS w1" if _w == "session_keys" else ""
    _add(f"packed_rows_{_w}", oracle.over_rows(_w, f"SELECT CAST(w >> 63 AS BIGINT) AS w0{_second}, n AS weight FROM rws"), _on(_w, lambda ctx: ctx.rows.select(*ctx.words, "weight")))
for _w in ("document_meta", "session_keys", "customer_orders"):
    _add(f"attribute_dim_{_w}", oracle.over_rows(_w, "SELECT a.rank, a.name, count(*) AS support, CAST(a.rank // 63 AS INT) AS word, CAST(CAST(1 AS BIGINT) << (62 - a.rank % 63) AS BIGINT) AS mask FROM attr a JOIN inc i ON i.name = a.name GROUP BY a.rank, a.name"), _on(_w, lambda ctx: ctx.attribute_table().select("rank", "name", "support", "word", "mask")))


# Families and the lattice.

for _w in ("conversation_shape", "nation_region"):
    _add(f"extents_{_w}", oracle.concepts(_w, "SELECT c.intent, k.obj FROM con c JOIN pk k ON (k.w & c.w) = c.w"), lambda spark, sf_dir, w=_w: (lambda r: derive.with_extents(r.context, r.concepts).select(r.context.string().alias("intent"), "obj"))(mined(spark, sf_dir, w)))
for _w in ("tiny", "document_meta", "conversation_shape", "nation_activity"):
    _add(
        f"covers_{_w}",
        oracle.concepts(_w, "SELECT c.intent AS child, p.intent AS parent FROM con c JOIN con p ON (c.w & p.w) = p.w AND c.w <> p.w WHERE NOT EXISTS (SELECT 1 FROM con b WHERE (c.w & b.w) = b.w AND (b.w & p.w) = p.w AND b.w <> c.w AND b.w <> p.w)"),
        lambda spark, sf_dir, w=_w: (lambda r: lattice.covers(r.context, r.concepts))(mined(spark, sf_dir, w)),
    )
def _shape(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Sizes are counted without a table of the family where the rows fit into a task."""
    ctx = context(spark, sf_dir, name)
    if len(ctx.words) == 1 and ctx.rows.count() <= central.MOST_ROWS:
        return lattice.running(sizes.counts_by_size(ctx))
    r = mined(spark, sf_dir, name)
    return lattice.levels(r.context, r.concepts)


for _w in ("lineitem_profile", "document_terms"):
    _add(f"lattice_shape_{_w}", oracle.concepts(_w, "SELECT size, count(*) AS concepts, CAST(sum(count(*)) OVER (ORDER BY size) AS BIGINT) AS running FROM con GROUP BY size"), lambda spark, sf_dir, w=_w: _shape(spark, sf_dir, w))
_add(
    "top_area_part_traits",
    oracle.concepts("part_traits", "SELECT intent, size, support, size * support AS area FROM con ORDER BY area DESC, intent LIMIT 25"),
    lambda spark, sf_dir: mined(spark, sf_dir, "part_traits").strings().withColumn("area", F.col("size") * F.col("support")).orderBy(F.desc("area"), "intent").limit(25),
)
_add(
    "concept_meet_join_nation_activity",
    oracle.concepts("nation_activity", f""", prs AS (SELECT a.w AS a, b.w AS b, a.w & b.w AS j, a.w | b.w AS u FROM con a JOIN con b ON a.w < b.w),
        mt AS (SELECT p.a, p.b, p.j, coalesce(bit_and(r.w), {_FULL}) AS m FROM prs p LEFT JOIN rws r ON (r.w & p.u) = p.u GROUP BY p.a, p.b, p.j)
        SELECT ca.intent AS a, cb.intent AS b, cm.intent AS meet, cj.intent AS "join" FROM mt JOIN con ca ON ca.w = mt.a JOIN con cb ON cb.w = mt.b JOIN con cm ON cm.w = mt.m JOIN con cj ON cj.w = mt.j"""),
    lambda spark, sf_dir: _meets(mined(spark, sf_dir, "nation_activity")),
)


def _meets(r: rounds.MiningResult) -> DataFrame:
    ctx = r.context
    side = lambda p: r.concepts.select(*[F.col(w).alias(f"{p}{i}") for i, w in enumerate(ctx.words)])
    pairs = side("a").crossJoin(side("b")).where(bits.lectic_less(ctx.columns("a"), ctx.columns("b")))
    return lattice.meets_and_joins(ctx, pairs).select(_names(ctx, "a").alias("a"), _names(ctx, "b").alias("b"), ctx.string().alias("meet"), _names(ctx, "j").alias("join"))


def _closed_pairs(r: rounds.MiningResult) -> DataFrame:
    ctx = r.context
    name = F.element_at(F.array(*[F.lit(a) for a in ctx.attributes]), F.col("rank") + 1)
    return derive.oplus(ctx, r.concepts).select(_names(ctx, "d").alias("d"), name.alias("p"), ctx.string().alias("closure"), "support")


def _tested(ctx: FormalContext) -> DataFrame:
    """Whether sets of attributes are concepts with all objects that have them."""
    out = []
    for text in _ASKED:
        names = text.split(",") if text else []
        last = ctx.sets([names]).select(derive.is_last(ctx)).first()[0]
        out.append((text, derive.is_concept(ctx, derive.objects_with(ctx, names), names), last))
    return ctx.spark.createDataFrame(out, "intent string, concept boolean, last boolean")


def _single_sets(ctx: FormalContext) -> DataFrame:
    return _attribute_seeds(ctx).select(*[F.col(f"s{i}").alias(w) for i, w in enumerate(ctx.words)])


def _local_extents(ctx: FormalContext) -> DataFrame:
    return derive.local_extents(ctx, _single_sets(ctx), F.pmod("obj", F.lit(3)).cast("int")).select(ctx.string().alias("intent"), "part", "obj")


def _extents_down(r: rounds.MiningResult) -> DataFrame:
    """All extents from the top concept downwards: each from the extent of one parent and one added attribute."""
    ctx, words = r.context, r.context.words
    d = bits.names_of("d", len(words))
    edges = lattice.lower_covers(ctx, r.concepts)
    added = bits.head_of([F.col(w).bitwiseAND(F.bitwise_not(F.col(x))) for w, x in zip(words, d, strict=True)], ctx.m)
    tree = settle(edges.groupBy(*words).agg(F.min(F.struct(*d)).alias("up")).select(*words, *[F.col(f"up.{x}").alias(x) for x in d]).withColumn("rank", added), "tree")
    top = rounds._start(ctx).select(*words)
    last = settle(top.join(ctx.objects.select("obj"), how="cross"), "extents")  # all objects have the top intent
    found, reached = last, top
    for _ in range(ctx.m):
        reached = reached.select(*[F.col(w).alias(x) for w, x in zip(words, d, strict=True)])
        step = settle(tree.join(reached, d, "left_semi"), "step")
        if step.isEmpty():
            break
        last = settle(derive.extents_from_parents(ctx, step, last), "extents")
        found, reached = found.unionByName(last), step.select(*words)
    return found.select(ctx.string().alias("intent"), "obj")


def _sampled(r: rounds.MiningResult) -> DataFrame:
    """Whether the family of a sample of half of the rows has intents, and all of them are intents of the whole."""
    ctx = r.context
    some = rounds.round_branch(ctx.sample(0.5)).strings().select("intent")
    return some.join(r.strings().select("intent", F.lit(1).alias("own")), "intent", "left").agg((F.count("*") > 0).alias("found"), (F.count("own") == F.count("*")).alias("inside"))


def _up(r: rounds.MiningResult) -> DataFrame:
    ctx = r.context
    last = r.concepts.where(derive.is_last(ctx)).select(*ctx.words)
    return lattice.paths_up(ctx, lattice.lower_covers(ctx, r.concepts), last).select(ctx.string().alias("intent"), "steps")


def _family_diff(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Intents that are lost when the English documents go."""
    ctx = context(spark, sf_dir, "document_meta")
    w, b = bits.mask(ctx.rank("lang=en"))
    fewer = replace(ctx, rows=settle(ctx.rows.where(F.col(f"w{w}").bitwiseAND(bits.long(b)) == 0), "rows"))
    return mined(spark, sf_dir, "document_meta").strings().select("intent").exceptAll(rounds.round_all(fewer).strings().select("intent"))


_add(
    "family_diff_document_meta",
    f"WITH RECURSIVE {oracle.concepts_cte(WORKLOADS['document_meta'])}, rows2 AS (SELECT DISTINCT w FROM pk WHERE ((w >> ({_T} - (SELECT rank FROM attr WHERE name = 'lang=en'))) & 1) = 0), fam2(w) AS (SELECT f FROM everything UNION SELECT f.w & r.w FROM fam2 f, rows2 r) SELECT intent FROM con WHERE w NOT IN (SELECT w FROM fam2)",
    _family_diff,
)

for _name, (_query, _sql) in (surroundings.QUERIES | streams.QUERIES).items():
    _add(_name, _sql, lambda spark, sf_dir, q=_query: q(spark, sf_dir, context, mined))


def queries() -> dict[str, Query]:
    return {name: e.query for name, e in ENTRIES.items()}


def oracle_sql() -> dict[str, str]:
    return {name: e.sql for name, e in ENTRIES.items() if e.sql}
