"""Bitmaps, their bound, and the theory of the bound."""

import random

import pytest
from pyspark.sql import functions as F

from setsim.functions import theory
from setsim.functions.bitmap import VARIANTS, BitmapSpec, attach, bit_string, choose_variant, exact_overlap, fold_words, hamming, overlap_bound, python_bitmap
from setsim.functions.spec import SimSpec
from setsim.plans.planner import choose_width


def test_bound_never_below_overlap():
    rng = random.Random(3)
    for _ in range(6000):
        b = rng.choice([4, 8, 16, 64])
        a, c = ([rng.randrange(200) for _ in range(rng.randint(1, 40))] for _ in "ac")
        a, c = sorted(set(a)), sorted(set(c))
        for v in VARIANTS:
            d = (python_bitmap([t % b for t in a], b, v) ^ python_bitmap([t % b for t in c], b, v)).bit_count()
            assert d <= len(set(a) ^ set(c))
            assert (len(a) + len(c) - d) // 2 >= len(set(a) & set(c))


def test_probe_bitmap_does_not_depend_on_order():
    rng = random.Random(4)
    for _ in range(300):
        slots = [rng.randrange(16) for _ in range(rng.randint(1, 20))]
        mixed = rng.sample(slots, len(slots))
        assert python_bitmap(slots, 16, "probe") == python_bitmap(mixed, 16, "probe")
        assert python_bitmap(slots, 16, "probe").bit_count() == min(16, len(slots))


@pytest.mark.parametrize("b", [16, 64, 128, 256])
@pytest.mark.parametrize("variant", VARIANTS)
def test_columns_equal_token_by_token(spark, variant, b):
    rng = random.Random(b)
    sets = [(i, sorted(rng.sample(range(1000), rng.randint(0, 90)))) for i in range(60)] + [(99, [63, 127, 191])]
    df = spark.createDataFrame(sets, "sid long, toks array<int>").withColumn("n", F.size("toks"))
    spec = BitmapSpec(variant, b)
    got = {r.sid: r.bits for r in attach(df, spec).select("sid", bit_string(spec.columns, b).alias("bits")).collect()}
    assert got == {i: format(python_bitmap([t % b for t in toks], b, variant), f"0{b}b") for i, toks in sets}


def test_worked_examples(spark):
    df = spark.createDataFrame([(1, [1, 5, 8], [3, 4, 5, 6])], "sid long, a array<int>, b array<int>")
    bits = BitmapSpec("or", 64)
    x = attach(df, bits, "a").withColumnRenamed("w0", "x")
    y = attach(x, bits, "b").withColumnRenamed("w0", "y")
    assert y.select(exact_overlap(["x"], ["y"])).first()[0] == 1
    rows = spark.createDataFrame([(10, 10, 0b1111, 0), (10, 10, 0b111111, 0)], "n int, m int, x long, y long")
    assert [r[0] for r in rows.select(overlap_bound("n", "m", hamming(["x"], ["y"]))).collect()] == [8, 7]
    assert spark.range(1).select(F.bit_count(F.lit(-1).cast("long"))).first()[0] == 64  # bit 63 counts


def test_wide_bitmaps_fold(spark):
    df = spark.createDataFrame([(1, [1, 65, 129, 200, 3])], "sid long, toks array<int>")
    for v in ("or", "xor"):
        wide, narrow = BitmapSpec(v, 256), BitmapSpec(v, 64)
        assert attach(df, wide).select(fold_words(wide.columns, v)).first()[0] == attach(df, narrow).select("w0").first()[0]


def test_variant_choice():
    j = lambda t: SimSpec.of("jaccard", t)
    assert [choose_variant(j(t)) for t in ("0.3", "0.5", "0.9")] == ["probe", "or", "xor"]
    assert [choose_variant(j(t), "literal") for t in ("0.5", "0.6", "0.8")] == ["probe", "or", "xor"]


def test_expected_bounds():
    assert theory.expected_bound("or", 64, 55) / 55 == pytest.approx(0.716, abs=5e-4)
    assert theory.expected_bound("xor", 64, 55) / 55 == pytest.approx(0.718, abs=5e-4)
    for n in (1, 10, 80):
        assert theory.expected_bound("xor", 64, n) == pytest.approx(theory.expected_bound_xor_sum(64, n), abs=1e-9)


def test_cutoffs():
    nine, eight = SimSpec.of("jaccard", "0.9"), SimSpec.of("jaccard", "0.8")
    assert theory.cutoff("or", 1024, nine) in (2128, 2129)
    assert theory.cutoff("xor", 1024, nine) == pytest.approx(4983, rel=0.03)
    assert theory.cutoff("xor", 1024, eight) / theory.cutoff("or", 1024, eight) == pytest.approx(1.47, abs=0.01)
    assert theory.cutoff("probe", 64, SimSpec.of("dice", "0.5")) == 32
    assert choose_width(10, eight) == 64 and choose_width(500, eight) > 64


@pytest.mark.parametrize("variant", VARIANTS)
def test_simulation_agrees(spark, variant):
    r = theory.simulate_bound(spark, variant, b=64, n=30, trials=4000).first()
    assert r.relative_error < 0.01
