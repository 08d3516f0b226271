"""The worked example, laws of closures, and agreement of all methods."""

import random
from dataclasses import replace

import pytest
from pyspark.sql import functions as F

from galoislake.functions import bits
from galoislake.operators import central, closure, derive, lattice
from galoislake.operators.context import build
from galoislake.plans import measures, rounds
from galoislake.sources.workloads import TINY, WORKLOADS

LECTIC = ["", "f", "e", "d", "df", "de", "cg", "b", "bf", "bd", "bdf", "bde", "bcfg", "bcdfg", "a", "ae", "adf", "adef", "aceg", "abdf", "abcdefg"]


def context(spark, sets, **options):
    rows = [(i, list(s)) for i, s in enumerate(sets)]
    return build(spark.createDataFrame(rows, "obj int, attrs array<string>"), **options)


def closed_sets(sets, attributes):
    """Every intersection of rows, and all attributes."""
    family = {frozenset(attributes)}
    for s in sets:
        family |= {f & frozenset(s) for f in family}
    return family


def found(result):
    return {frozenset(r.intent.split(",")) - {""}: r.support for r in result.strings().collect()}


@pytest.fixture(scope="module")
def tiny(spark):
    return WORKLOADS["tiny"].context(spark, "")


def test_worked_example(spark, tiny):
    single = rounds.round_single(tiny, 2)
    steps = [r.s.replace(",", "") for r in single.concepts.select("round", tiny.string().alias("s")).orderBy("round").collect()]
    assert steps == LECTIC and single.rounds == 20
    every = rounds.round_all(tiny, parts=2)
    assert [m["new"] for m in every.metrics] == [6, 12, 2, 0] and every.productive_rounds == 3
    assert (sum(m["pairs"] for m in every.metrics), sum(m["seeds"] for m in every.metrics)) == (93, 68)
    branch = rounds.round_branch(tiny)
    assert [m["new"] for m in branch.metrics] == [6, 9, 5, 0] and sum(m["seeds"] for m in branch.metrics) == 50
    assert found(every) == found(branch)
    assert central.branch_scan(tiny, "prefix")._emitted == 63
    extents = {(r.s.replace(",", ""), r.obj) for r in derive.with_extents(tiny, every.concepts).select(tiny.string().alias("s"), "obj").collect()}
    assert extents == {(i, k) for i in LECTIC for k, row in TINY.items() if set(i) <= set(row)}


def test_merge_of_local_closures(spark, tiny):
    part = F.when(F.col("obj") <= 3, 0).otherwise(1)
    rows = tiny.objects.withColumn("part", part).withColumn("weight", F.lit(1).cast("long"))
    split = replace(tiny, rows=rows, parts=2)
    seed = tiny.sets(["bd"]).toDF("s0")
    local = {r.part: r.s for r in closure.local_closures(split, seed).select("part", tiny.string().alias("s")).collect()}
    assert local == {0: "b,d,f", 1: "b,d,e"}
    assert closure.close(tiny, seed).select(tiny.string().alias("s")).first().s == "b,d"
    plus = {(r.d, r["rank"]): r.s for r in derive.oplus(tiny, tiny.sets(["adf", "adef"])).select(bits.intent_string([F.col("d0")], tiny.attributes).alias("d"), "rank", tiny.string().alias("s")).collect()}
    assert plus["a,d,f", 4] == "a,d,e,f" and plus["a,d,e,f", 2] == "a,c,e,g"


def test_derivations(spark, tiny):
    objs = spark.createDataFrame([(1,), (5,)], "obj int")
    assert tuple(derive.common_attributes(tiny, objs).first()) == tiny.pack("adf")
    assert {r.obj for r in derive.objects_with(tiny, list("bf")).collect()} == {1, 3, 6}
    assert {r.obj for r in derive.close_objects(tiny, spark.createDataFrame([(1,), (3,)], "obj int")).collect()} == {1, 3}
    assert derive.is_concept(tiny, objs, list("adf")) and not derive.is_concept(tiny, objs, list("ad"))
    assert derive.bottom_intent(tiny) == (0,)


EDGES = {
    "no objects": ([], None),
    "no attributes": ([[], []], None),
    "an empty row": ([["a", "b"], [], ["b"]], None),
    "attribute of all": ([["a", "b"], ["a", "c"]], None),
    "unused attribute": ([["a"], ["b"]], ["a", "b", "z"]),
    "equal rows and columns": ([["a", "b"], ["a", "b"], ["a", "b", "c", "d"]], None),
    "one object": ([["a", "b"]], None),
    "nulls and repeats": ([["a", None, "a"], ["b"]], None),
}


@pytest.mark.parametrize("case", EDGES)
def test_edges(spark, case):
    sets, explicit = EDGES[case]
    ctx = context(spark, sets, explicit=explicit)
    clean = [frozenset(x for x in s if x) for s in sets]
    want = {f: sum(f <= s for s in clean) for f in closed_sets(clean, ctx.attributes)}
    assert found(rounds.round_all(ctx)) == want
    assert found(rounds.round_branch(ctx)) == want
    for frame in (central.lectic_scan(ctx), central.branch_scan(ctx), central.branch_subtrees(ctx)):
        assert {frozenset(r.intent.split(",")) - {""}: r.support for r in frame.select(ctx.string().alias("intent"), "support").collect()} == want


@pytest.mark.parametrize("m", [9, 63, 70])
def test_methods_and_strategies_agree(spark, m):
    rng = random.Random(m)
    sets = [[f"a{k:03}" for k in range(m) if rng.random() < 2.5 / m] for _ in range(40)]
    ctx = context(spark, sets, explicit=[f"a{k:03}" for k in range(m)])
    want = {f: sum(f <= frozenset(s) for s in sets) for f in closed_sets(sets, ctx.attributes)}
    for options in ({}, {"strategy": "join"}, {"strategy": "blocks"}, {"strategy": "postings"}, {"registry": "flat"}, {"dedupe_seeds": False}, {"static": "reload", "parts": 5}):
        assert found(rounds.round_all(ctx, **options)) == want, options
    assert found(rounds.round_branch(ctx, parts=3)) == want
    family = None
    dealt = ctx.rows.withColumn("b", F.pmod(F.xxhash64(*ctx.words), F.lit(3)))
    for k in range(3):
        family = lattice.update_intents(family, dealt.where(F.col("b") == k), ctx.full)
    assert {frozenset(r.s.split(",")) - {""} for r in family.select(ctx.string().alias("s")).collect()} == set(want)


@pytest.mark.parametrize("how", ["hash", "block", "round_robin", "density"])
@pytest.mark.parametrize("parts", [1, 3, 11])
def test_parts_merge_to_the_closure(spark, how, parts):
    rng = random.Random(parts)
    ctx = context(spark, [[x for x in "abcdef" if rng.random() < 0.5] for _ in range(30)])
    split = ctx.split(parts, how)
    assert split.rows.count() == ctx.rows.count() and split.rows.agg(F.max("part")).first()[0] < parts
    seeds = ctx.spark.createDataFrame([ctx.pack(s) for s in ("", "a", "bc", "abf", "abcdef")], "s0 long")
    merged = {r.s0: r.w0 for r in closure.merge_local(split, closure.local_closures(split, seeds)).collect()}
    assert merged == {r.s0: r.w0 for r in closure.close(ctx, seeds).collect()}


def test_closure_laws(spark):
    rng = random.Random(5)
    ctx = context(spark, [[x for x in "abcdefgh" if rng.random() < 0.5] for _ in range(25)])
    close = {r.s0: r.w0 for r in closure.close(ctx, ctx.spark.range(256).select(F.shiftleft("id", 55).alias("s0"))).collect()}
    for s, c in close.items():
        assert c & s == s and close[c] == c
        assert all(close[t] & c == c for t in close if t & s == s)


def test_guards(spark, tiny):
    with pytest.raises(rounds.TooManyIntents):
        rounds.round_all(tiny, max_intents=5)
    with pytest.raises(ValueError):
        rounds.round_all(tiny, registry="none")
    with pytest.raises(ValueError):
        central.local(tiny, most=3)
    assert rounds.round_all(tiny, max_rounds=1).rounds == 1


def test_order_of_attributes_changes_no_family(spark):
    sets = [list(v) for v in TINY.values()]
    want = found(rounds.round_all(context(spark, sets)))
    for options in ({"order": "support"}, {"order": "support_desc"}, {"explicit": list("gfedcba")}):
        assert found(rounds.round_all(context(spark, sets, **options))) == want


def test_covers_are_the_lattice_order(spark, tiny):
    got = {(r.child, r.parent) for r in lattice.covers(tiny, rounds.round_all(tiny).concepts).collect()}
    sets = {",".join(s): frozenset(s) for s in LECTIC}
    below = {(a, b) for a in sets for b in sets if sets[b] < sets[a]}
    assert got == {(a, b) for a, b in below if not any((a, c) in below and (c, b) in below for c in sets)}


def test_measures(spark):
    curve = measures.scaling_curve(spark, [(1, 10.0), (2, 6.0), (4, 4.0)]).orderBy("parts").collect()
    assert [round(r.speed_up, 2) for r in curve] == [1.0, 1.67, 2.5] and [round(r.efficiency, 2) for r in curve] == [1.0, 0.83, 0.62]
    assert measures.best_parts([(1, 10.0), (2, 6.0), (4, 7.0)]) == 2 and measures.saving(2, 8) == 0.75 and measures.ratio(2, 8) == 4


@pytest.mark.parametrize("name, all_new, branch_new", [
    ("lineitem_profile", [20, 153, 550, 951, 630, 0], [20, 153, 550, 951, 630, 0]),
    ("conversation_shape", [8, 6, 0], [2, 2, 2, 2, 2, 2, 2, 0]),
    ("benchmark_terms", [53, 22, 0], [53, 22, 0]),
    ("nation_activity", [5, 1, 0], [5, 1, 0]),
])
def test_rounds_on_given_tables(spark, name, all_new, branch_new):
    ctx = WORKLOADS[name].context(spark, "/root/testdata/sf0.01")
    assert [m["new"] for m in rounds.round_all(ctx).metrics] == all_new
    assert [m["new"] for m in rounds.round_branch(ctx).metrics] == branch_new


def test_plan_merges_before_the_exchange(spark, tiny, capsys):
    closure.close(tiny, tiny.sets(["a"]).toDF("s0"), "join").explain()
    plan = capsys.readouterr().out
    assert "partial_bit_and" in plan and "BroadcastNestedLoopJoin" in plan
