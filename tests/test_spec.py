"""Exact thresholds, bounds and filters on integers and as columns."""

import random
from fractions import Fraction

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from setsim.functions.spec import SimSpec
from setsim.operators.filters import suffix_bound

SPECS = [SimSpec.of(m, t) for m, ts in (("jaccard", ("0.5", "0.6", "0.8", "0.95", "1")), ("cosine", ("0.5", "0.8")), ("dice", ("0.6", "0.9")), ("overlap", ("1", "4"))) for t in ts]


def test_parsing():
    assert SimSpec.of("jaccard", "0.8") == SimSpec("jaccard", 4, 5)
    assert SimSpec.of("jaccard", 0.75) == SimSpec("jaccard", 3, 4)
    for bad in (("jaccard", "0"), ("jaccard", "1.2"), ("overlap", "0.5"), ("overlap", "0"), ("hamming", "1")):
        with pytest.raises(ValueError):
            SimSpec.of(*bad)


def test_worked_examples():
    four = SimSpec.of("overlap", "4")
    assert (four.prefix_len(7), four.prefix_len(5)) == (4, 2)
    assert (four.prefix_len(7, 2), four.prefix_len(5, 2)) == (5, 3)
    six = SimSpec.of("jaccard", "0.6")
    assert (six.prefix_len(7), six.prefix_len(6)) == (3, 3)
    assert six.need(7, 6) > 4  # a first match at the third of six leaves four at most: pruned
    assert SimSpec.of("jaccard", "0.8").prefix_len(5) == 2  # floating point gives 1 here
    assert four.prefix_len(3) == 0  # too small for any partner


@settings(max_examples=300, deadline=None)
@given(st.sampled_from(SPECS), st.integers(1, 300), st.integers(1, 300), st.integers(0, 300))
def test_need_and_partners_follow_from_acceptance(spec, n, m, o):
    o = min(o, n, m)
    assert spec.accepts(o, n, m) == (o >= spec.need(n, m) and o > 0)
    if spec.accepts(o, n, m):
        assert spec.least_partner(n) <= m
        top = spec.largest_partner(n)
        assert top is None or m <= top
        assert spec.least_overlap(n) <= o


def test_columns_equal_integers(spark):
    pairs = [(n, m, o) for n in (1, 2, 3, 5, 8, 21, 99, 1000, 40425) for m in (1, 2, 4, 5, 9, 22, 100, 999, 40000) for o in (0, 1, min(n, m) // 2, min(n, m))]
    df = spark.createDataFrame(pairs, "n int, m int, o int")
    for spec in SPECS:
        sized = df.withColumns({"s": F.least("n", "m"), "l": F.greatest("n", "m")})
        got = sized.select("n", "m", "o", spec.need_col("n", "m").alias("need"), spec.accepts_col("o", "n", "m").alias("ok"), spec.prefix_len_col("n").alias("k"), spec.length_ok_col("s", "l").alias("len"))
        for r in got.collect():
            assert r.need == spec.need(r.n, r.m), (spec, r)
            assert r.ok == spec.accepts(r.o, r.n, r.m), (spec, r)
            assert r.k == spec.prefix_len(r.n), (spec, r)
            assert r.len == (spec.least_partner(max(r.n, r.m)) <= min(r.n, r.m)), (spec, r)


def test_filters_keep_similar_pairs():
    rng = random.Random(5)
    for _ in range(4000):
        spec = rng.choice(SPECS)
        universe = rng.randint(4, 40)
        a, b = (sorted(rng.sample(range(universe), rng.randint(1, universe))) for _ in "ab")
        common = sorted(set(a) & set(b))
        if not spec.accepts(len(common), len(a), len(b)):
            continue
        for ell in (1, 2, 3):
            both = set(a[: spec.prefix_len(len(a), ell)]) & set(b[: spec.prefix_len(len(b), ell)])
            assert len(both) >= min(ell, spec.need(len(a), len(b)))
        first = min(set(a[: spec.prefix_len(len(a))]) & set(b[: spec.prefix_len(len(b))]))
        i, j = a.index(first), b.index(first)
        assert min(len(a) - i, len(b) - j) >= spec.need(len(a), len(b))
        for depth in (0, 1, 2, 4):
            assert 1 + suffix_bound(a[i + 1 :], b[j + 1 :], depth) >= spec.need(len(a), len(b))


def test_suffix_example():
    # seven tokens each, first match at the front, tails split at a common probe into 2/3 and 1/3 tokens: 1 + 1 + 1 + 2 = 5 < 6
    r, s = [1, 2, 50, 60, 70, 80], [5, 50, 90, 91]
    assert 1 + suffix_bound(r, s, 1) <= 5


def test_thresholds_are_fractions():
    assert Fraction(SimSpec.of("jaccard", "0.85").num, SimSpec.of("jaccard", "0.85").den) == Fraction(17, 20)
