"""Closures that share extents, families that do not stay on the driver, contexts from pairs."""

import random

import numpy as np
import pytest

from galoislake.functions import bits
from galoislake.operators import central, closure
from galoislake.operators.context import build, build_from_pairs
from galoislake.operators.extents import Rows


def made(n, m, seed, most=6):
    rng = random.Random(seed)
    sets = {frozenset(rng.sample(range(m), rng.randint(0, min(m, most)))) for _ in range(n)}
    return [sorted(s) for s in sorted(sets, key=sorted)]


def packed(sets, m):
    return np.array([bits.pack(s, bits.width(m)) for s in sets], dtype=np.int64).reshape(-1, bits.width(m))


@pytest.mark.parametrize("n,m", [(0, 4), (1, 1), (40, 7), (300, 63), (300, 64), (500, 130)])
def test_close_equals_plain_intersection(n, m):
    sets = made(n, m, n + m)
    weights = np.arange(1, len(sets) + 1)
    seeds = [[], list(range(m))] + [s[:k] for s in sets for k in range(len(s) + 1)] + made(60, m, 5, 3)
    got, support = Rows(packed(sets, m), weights, m).close(packed(seeds, m))
    for s, c, n_ in zip(seeds, got, support, strict=True):
        held = [k for k, row in enumerate(sets) if set(s) <= set(row)]
        want = set(range(m)).intersection(*[sets[k] for k in held]) if held else set(range(m))
        assert (tuple(c), n_) == (bits.pack(want, bits.width(m)), sum(int(weights[k]) for k in held))


@pytest.mark.parametrize("n,m", [(0, 3), (1, 1), (60, 8), (80, 70)])
def test_walks_find_every_intent_once(n, m):
    sets = made(n, m, 3 * n + m, 4)
    rows = Rows(packed(sets, m), np.ones(len(sets)), m)
    want = {tuple(bits.full_words(m))}
    for row in packed(sets, m):
        want |= {tuple(int(x) for x in np.bitwise_and(f, row)) for f in want}
    walked = [tuple(x) for b in rows.walk() for x in b.sets.tolist()]
    assert sorted(walked) == sorted(want) == [tuple(x.tolist()) for x, _ in rows.lectic()]


def test_long_families_leave_the_driver(spark, monkeypatch):
    sets = [[f"a{x:02}" for x in s] for s in made(60, 9, 1)]
    ctx = build(spark.createDataFrame([(i, s) for i, s in enumerate(sets)], "obj int, attrs array<string>"))
    whole = {tuple(r) for r in central.branch_scan(ctx).collect()}
    steps = [tuple(r) for r in central.lectic_scan(ctx).orderBy("step").collect()]
    monkeypatch.setattr(central, "AT_ONCE", 7)
    written = central.branch_scan(ctx)
    assert written.inputFiles() and {tuple(r) for r in written.collect()} == whole and len(whole) > 7
    assert [tuple(r) for r in central.lectic_scan(ctx).orderBy("step").collect()] == steps


def test_context_from_pairs(spark):
    profiles = [(1, ["b", "a"]), (2, []), (3, ["b", None]), (4, ["b", "a"])]
    pairs = [(1, "b"), (1, "a"), (1, "a"), (2, None), (3, "b"), (3, None), (4, "a"), (4, "b")]
    want = build(spark.createDataFrame(profiles, "obj int, attrs array<string>"))
    got = build_from_pairs(spark.createDataFrame(pairs, "obj int, name string"))
    assert got.attributes == want.attributes == ("a", "b")
    assert sorted(got.rows.collect()) == sorted(want.rows.collect()) and sorted(got.objects.collect()) == sorted(want.objects.collect())
    none = build_from_pairs(spark.createDataFrame([(1, None)], "obj int, name string"))
    assert none.attributes == () and [tuple(r) for r in none.rows.collect()] == [(0, 1)]


def test_blocks_do_not_lose_seeds_over_their_borders(spark):
    sets = [[f"a{x:03}" for x in s] for s in made(400, 70, 2)]
    ctx = build(spark.createDataFrame([(i, s) for i, s in enumerate(sets)], "obj int, attrs array<string>"))
    seeds = ctx.sets([s[:2] for s in sets]).distinct().toDF("s0", "s1")
    plain = {tuple(r) for r in closure.close(ctx, seeds, "join").collect()}
    assert {tuple(r) for r in closure._by_blocks(ctx, seeds, 37, 11).collect()} == plain


def test_tiny_queries_read_the_customers(spark, tmp_path):
    import __spark_entry__ as entry

    spark.createDataFrame([(1, "BUILDING", -5.0), (2, "BUILDING", 10.0)], "c_custkey long, c_mktsegment string, c_acctbal double").write.parquet(str(tmp_path / "customer.parquet"))
    assert [tuple(r) for r in entry.queries()["bottom_intent_tiny"](spark, str(tmp_path)).collect()] == [("seg=BUILDING", 1, 2)]


def test_keyed_state_takes_few_files(spark, monkeypatch):
    import glob

    import __spark_entry__ as entry
    from galoislake.streaming import queries

    paths, plain = {}, queries.new_path
    monkeypatch.setattr(queries, "new_path", lambda s, name: paths.setdefault(name, plain(s, name)) if name == "closed" else plain(s, name))
    entry.queries()["stream_common_by_user"](spark, "/root/testdata/sf0.001")
    batches = glob.glob(paths["closed"].removeprefix("file:") + "/batch=*")
    assert batches and all(len(glob.glob(b + "/part-*")) <= queries.STATE_FILES for b in batches)
