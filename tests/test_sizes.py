"""Counts of intents by size, against every intersection of rows."""

import random
from collections import Counter

import numpy as np

from galoislake.operators import sizes
from galoislake.plans import catalogue
from tests.test_mining import closed_sets, context


def test_counts_by_size_are_those_of_all_intersections(spark):
    rng = random.Random(5)
    names = "abcdefghij"
    cases = [[], [""], ["ab", ""], [names], *([["".join(sorted(rng.sample(names, rng.randint(0, 9)))) for _ in range(n)] for n in (3, 12, 40)])]
    for sets in cases:
        want = Counter(map(len, closed_sets(sets, set().union(*sets))))
        ctx = context(spark, sets)
        for most in (1, 6, sizes.MOST):
            got = sizes.counts_by_size(ctx, most=most).collect()
            assert {r.size: r.concepts for r in got} == want and len(got) == len(want)


def test_many_rows_and_all_word_bits():
    rng = np.random.default_rng(8)
    rows = np.unique(np.bitwise_or.reduce(np.int64(1) << rng.integers(0, 63, (600, 3)), axis=1))
    family = {(1 << 63) - 1}
    for r in rows.tolist():
        family |= {f & r for f in family}
    node = (sizes._rare_first(rows, 63), int(np.bitwise_and.reduce(rows)), -1)
    want = Counter(f.bit_count() for f in family) - Counter([63])
    for most in (4, sizes.MOST):
        assert {k: n for k, n in enumerate(sizes.subtree_sizes(node, 63, most).tolist()) if n} == want


def test_the_shape_of_document_terms_mines_no_family(spark, monkeypatch):
    def refused(*_):
        raise AssertionError("the family was mined")

    monkeypatch.setattr(catalogue, "mined", refused)
    got = catalogue.queries()["lattice_shape_document_terms"](spark, "/root/testdata/sf0.01").collect()
    assert sum(r.concepts for r in got) == max(r.running for r in got) == 4478


def test_subtrees_of_few_rows_are_counted_by_tables_of_their_rows():
    rng = np.random.default_rng(3)
    words = rng.integers(0, 1 << 63, (64, 5), dtype=np.uint64)
    flags = np.array([[[int(x) >> i & 1 for i in range(64)] for x in column] for column in words.T])
    turned = np.array([[[int(x) >> i & 1 for i in range(64)] for x in column] for column in sizes._transposed(words.copy()).T])
    assert (turned == flags.transpose(0, 2, 1)).all()
    for n, m in ((1, 5), (2, 63), (8, 20), (9, 63), (64, 12), (65, 12), (130, 10)):
        rows = np.unique(np.packbits(rng.random((n, 64)) < 0.5, axis=1).view(">u8").ravel().astype(np.int64) & (1 << 63) - (1 << 63 - m))
        family = set()
        for r in rows.tolist():
            family |= {f & r for f in family} | {r}
        want = Counter(f.bit_count() for f in family)
        for most in (256, sizes.MOST):
            got = sizes.subtree_sizes((rows, int(np.bitwise_and.reduce(rows)), -1), m, most)
            assert {k: c for k, c in enumerate(got.tolist()) if c} == want
