"""Packing and set expressions, on random sets over one and two words."""

import random

import pytest
from pyspark.sql import functions as F

from galoislake.functions import bits


@pytest.mark.parametrize("m", [1, 7, 62, 63, 64, 126, 127])
def test_words_keep_lectic_order_and_tests(spark, m):
    rng = random.Random(m)
    sets = [frozenset(r for r in range(m) if rng.random() < 0.4) for _ in range(12)] + [frozenset(), frozenset(range(m))]
    words = bits.width(m)
    assert all(bits.unpack(bits.pack(s, words)) == sorted(s) for s in sets)
    rows = [(i, j, *bits.pack(a, words), *bits.pack(b, words), rng.randrange(m)) for i, a in enumerate(sets) for j, b in enumerate(sets)]
    schema = "i int, j int, " + ", ".join(f"a{k} long" for k in range(words)) + ", " + ", ".join(f"b{k} long" for k in range(words)) + ", p int"
    a, b = ([F.col(f"{x}{k}") for k in range(words)] for x in "ab")
    p = F.col("p")
    got = spark.createDataFrame(rows, schema).select(
        "i", "j", "p", bits.lectic_less(a, b).alias("less"), bits.lectic_less_at(a, b, p).alias("at"), bits.contains(a, b).alias("inside"), bits.disjoint(a, b).alias("apart"),
        bits.overlap(a, b).alias("shared"), bits.size_of(a).alias("size"), bits.head_of(a, m).alias("head"), F.array(*bits.seed_words(a, p)).alias("seed"), bits.has_rank(a, p).alias("has"),
    )
    for r in got.collect():
        x, y = sets[r.i], sets[r.j]
        differ = sorted(x ^ y)
        assert r.less == bool(differ and differ[0] in y)
        assert r["at"] == bool(differ and differ[0] == r.p and r.p in y)
        assert (r.inside, r.apart, r.shared, r.size, r.has) == (y <= x, not x & y, len(x & y), len(x), r.p in x)
        assert r.head == min(x, default=m)
        assert tuple(r.seed) == bits.pack({q for q in x if q < r.p} | {r.p}, words)


def test_names_are_escaped(spark):
    row = spark.createDataFrame([(bits.pack([0, 1, 2], 1)[0],)], "w0 long").select(bits.intent_string([F.col("w0")], ["a,b", "c\\d", "é"]).alias("s")).first()
    assert row.s == "a\\,b,c\\\\d,é"
