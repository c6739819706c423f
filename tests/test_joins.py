"""Every method equals the unfiltered join, with and without the bitmap filter."""

import random

import pytest
from pyspark.sql import functions as F

from setsim.functions.bitmap import BitmapSpec
from setsim.functions.spec import SimSpec
from setsim.functions.tokens import qgrams
from setsim.operators import joins
from setsim.operators.components import connected_components
from setsim.operators.order import prepare, prepare_pair
from setsim.plans import metrics, planner
from setsim.sources.io import load_collection, read_sets, save_collection
from setsim.sources.workloads import from_arrays, order_parts

METHODS = [("prefix_length", {"dedup": "array"}), ("prefix_length", {"dedup": "minrank"}), ("prefix_positional", {}), ("prefix_suffix", {}), ("ell_prefix", {"ell": 1}), ("ell_prefix", {"ell": 2}), ("ell_prefix", {"ell": 3}), ("grouped_prefix", {}), ("block", {}), ("block", {"cap": 2}), ("block", {"kernel": "expr"})]
SPREAD = [("prefix_length", {"size_key": True}), ("prefix_positional", {"hot_df": 3}), ("prefix_suffix", {"suffix_depth": 3, "hot_df": 5, "size_key": True}), ("ell_prefix", {"ell": 2, "hot_df": 3, "size_key": True}), ("grouped_prefix", {"hot_df": 3, "size_key": True}), ("prefix_positional", {"hbf_at": "kernel"}), ("prefix_length", {"collapse": True}), ("grouped_prefix", {"collapse": True})]


def _sets(seed, n=70, universe=30, most=14):
    rng = random.Random(seed)
    base = [sorted(rng.sample(range(universe), rng.randint(1, most))) for _ in range(n)]
    for _ in range(n // 3):  # near copies and copies
        s = set(rng.choice(base))
        if rng.random() < 0.6:
            s ^= {rng.randrange(universe)}
        base.append(sorted(s or {0}))
    return [(i, [f"t{x:03d}" for x in s]) for i, s in enumerate(base)]


def _long(spark, sets):
    return from_arrays(spark.createDataFrame(sets, "sid long, ts array<string>"), "sid", F.col("ts"))


def _brute(sets, spec, other=None):
    out = set()
    for i, a in sets:
        for j, b in other if other is not None else sets:
            if other is None and j <= i:
                continue
            o = len(set(a) & set(b))
            if spec.accepts(o, len(set(a)), len(set(b))):
                out.add((i, j, len(set(a)), len(set(b)), o))
    return out


def _rows(df):
    rows = df.select("id_l", "id_r", "n_l", "n_r", "overlap").collect()
    assert len(rows) == len(set(rows))
    return {tuple(r) for r in rows}


@pytest.fixture(scope="module")
def small(spark):
    sets = _sets(1)
    return sets, prepare(_long(spark, sets))


@pytest.mark.parametrize("measure,threshold", [("jaccard", "0.5"), ("jaccard", "0.8"), ("jaccard", "1"), ("cosine", "0.7"), ("dice", "0.75"), ("overlap", "3")])
def test_self_join(small, measure, threshold):
    sets, c = small
    spec = SimSpec.of(measure, threshold)
    want = _brute(sets, spec)
    assert _rows(joins.naive(c, None, spec)) == want
    picked = METHODS if (measure, threshold) == ("jaccard", "0.5") else METHODS[:1] + METHODS[2:4] + METHODS[5:6] + METHODS[7:9]
    for k, (method, options) in enumerate(picked):
        for bitmap in (None, BitmapSpec("auto" if k % 2 else "xor", 16 if k % 3 else 64)):
            assert _rows(joins.join_collections(c, None, spec, method, bitmap=bitmap, **options)) == want, (method, options, bitmap)


@pytest.mark.parametrize("measure,threshold", [("jaccard", "0.6"), ("cosine", "0.8"), ("dice", "0.75"), ("overlap", "3"), ("jaccard", "1")])
def test_spread_joins(small, monkeypatch, measure, threshold):
    """Blocks of hot tokens and large groups, size buckets, the kernel filter and collapsed classes change no result."""
    monkeypatch.setattr(joins.cand, "GROUP_BLOCK", 2)
    sets, c = small
    spec = SimSpec.of(measure, threshold)
    want = _brute(sets, spec)
    for method, options in SPREAD if threshold == "0.6" else SPREAD[3:5]:
        for bitmap in (None, BitmapSpec("xor", 64)):
            assert _rows(joins.join_collections(c, None, spec, method, bitmap=bitmap, **options)) == want, (method, options, bitmap)


def test_hot_token_is_dealt_out(spark):
    """A token of every set: no join key holds more than its share of the postings."""
    rng = random.Random(4)
    sets = [(i, ["hot", *(f"r{rng.randrange(40)}" for _ in range(3))]) for i in range(600)]
    c = prepare(_long(spark, sets))
    spec = SimSpec.of("jaccard", "0.2")
    p = joins.cand.prefix_postings(c.sets, spec)
    left, right = joins.cand._salted(*joins.cand._bucketed(p, p, spec, True), c.hot(50))
    top = lambda df: df.groupBy("rank", "z", "salt").count().agg(F.max("count")).first()[0]
    assert right.count() == p.count() and top(right) < 2.5 * 50 < p.groupBy("rank").count().agg(F.max("count")).first()[0]
    assert left.groupBy("rank", "z", "salt", "sid").count().filter("count > 1").isEmpty()
    want = _rows(joins.join_collections(c, None, spec))
    assert _rows(joins.join_collections(c, None, spec, hot_df=50, size_key=True)) == want


def test_join_of_two_collections(spark):
    left = _sets(2, 40)
    right = _sets(3, 30) + [(500 + i, s) for i, s in left[:25]]
    spec = SimSpec.of("jaccard", "0.6")
    want = _brute(left, spec, right)
    assert want
    a, b = prepare_pair(_long(spark, left), _long(spark, right))
    for method, options in METHODS[:1] + METHODS[2:4] + METHODS[5:6] + METHODS[7:9] + SPREAD[3:5]:
        for bitmap in (None, BitmapSpec("or", 64)):
            assert _rows(joins.join_collections(a, b, spec, method, bitmap=bitmap, **options)) == want, (method, bitmap)
    same, again = prepare_pair(_long(spark, left), _long(spark, left))
    both = _rows(joins.join_collections(same, again, spec))
    own = _rows(joins.join_collections(same, None, spec))
    assert {r[:2] for r in both if r[0] < r[1]} == {r[:2] for r in own} and len(both) == 2 * len(own) + len(left)


def test_variants_verifiers_and_placement(small):
    sets, c = small
    spec = SimSpec.of("jaccard", "0.6")
    want = _brute(sets, spec)
    for v in ("or", "xor", "probe"):
        for at in ("pre", "post"):
            assert _rows(joins.join_collections(c, None, spec, bitmap=BitmapSpec(v, 64), hbf_at=at)) == want
    for how in ("merge_stop", "relational", "bitset"):
        assert _rows(joins.join_collections(c, None, spec, verify=how, universe=64)) == want
    assert _rows(joins.join_collections(c, None, spec, "ell_prefix", ell="adaptive", bitmap=True)) == want
    assert _rows(joins.join_collections(c, None, spec, "ell_prefix", ell=2, bitmap=True, hbf_levels="first")) == want
    assert _rows(joins.naive(c, None, spec, "nested_loop")) == want
    assert metrics.lost_pairs(c, spec, "prefix_length", bitmap=True).isEmpty()


def test_corner_sets(spark):
    sets = [(1, ["a"]), (2, ["a"]), (3, []), (4, ["a", "a", "b", None]), (5, ["b", "a"]), (6, ["z"])]
    long = _long(spark, sets)
    got = _rows(joins.similarity_join(long, threshold="1"))
    assert got == {(1, 2, 1, 1, 1), (4, 5, 2, 2, 2)}
    assert _rows(joins.similarity_join(long, threshold="1", method="ell_prefix", ell=2)) == got
    assert joins.similarity_join(long.limit(0), threshold="0.5").isEmpty()


def test_bigram_examples(spark):
    df = spark.createDataFrame([("Data Warehouse",), ("Databases",), ("Databazes",), (None,), ("x",)], "t string")
    got = [r[0] for r in df.select(qgrams("t", 2)).collect()]
    assert len(set(got[0])) == 13 and sum(" " in g for g in got[0]) == 2
    assert len(got[1]) == len(got[2]) == 8 and len(set(got[1]) & set(got[2])) == 6
    assert got[4] == []


def test_around(small, spark):
    sets, c = small
    pairs = joins.join_collections(c, None, SimSpec.of("jaccard", "0.7")).cache()
    ids = {x for r in pairs.collect() for x in (r.id_l, r.id_r)}
    assert {r.sid for r in joins.twins(c.sets, pairs).collect()} == ids
    assert {r.sid for r in joins.without_twin(c.sets, pairs).collect()} == {i for i, _ in sets} - ids
    assert joins.top_pairs(pairs, 3).count() == 3
    assert joins.top_partners(pairs, 1).groupBy("id").count().filter("count > 1").isEmpty()
    classes, members = joins.collapse_equal(c)
    assert members.count() == len(sets) and classes.sets.count() == len({tuple(s) for _, s in sets})
    kept = joins.keep_one_per_cluster(c.sets, pairs).count()
    assert kept == len(sets) - len(ids) + joins.components(pairs).select("component").distinct().count()


def test_components(spark):
    rng = random.Random(9)
    path = [(i, i + 1) for i in range(60)]
    star = [(1000, 1000 + i) for i in range(1, 80)]
    noise = [(rng.randrange(2000, 2100), rng.randrange(2000, 2100)) for _ in range(70)]
    edges = path + star + noise + [(5, 5), (None, 3), (1, 0)]
    parent = {}

    def find(x):
        parent.setdefault(x, x)
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in path + star + [e for e in noise if e[0] != e[1]]:
        a, b = find(a), find(b)
        parent[max(a, b)] = min(a, b)
    got = {r.node: r.component for r in connected_components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {x: find(x) for x in parent}
    assert connected_components(spark.createDataFrame([], "a long, b long")).isEmpty()


def test_given_tables(spark, sf):
    c = prepare(order_parts(spark, sf))
    spec = SimSpec.of("jaccard", "0.5")
    counts = metrics.stage_counts(c, spec, BitmapSpec("xor", 64, cutoff=None)).first()
    assert counts.similar == joins.naive(c, None, spec).count()
    assert counts.candidates - counts.pruned == counts.verified and counts.pruned / counts.candidates > 0.9
    assert planner.plan(c, spec).method in joins.METHODS


def test_saved_collections(spark, small, tmp_path):
    _, c = small
    save_collection(c.sets, str(tmp_path / "sets"))
    back = load_collection(spark, str(tmp_path / "sets"), 3, 9)
    assert {r.sid for r in back.collect()} == {r.sid for r in c.sets.filter("n BETWEEN 3 AND 9").collect()}
    (tmp_path / "in.csv").write_text("sid,tok\n1,a\n1,b\n2,a\n2,a\n")
    assert read_sets(spark, str(tmp_path / "in.csv"), "sid", "tok", format="csv", exploded=True, header=True).count() == 3


def test_plan_is_lean(spark, small):
    """The candidate join runs on slim postings: no tokens beside the prefix, the bound inside the join."""
    _, c = small
    plan = joins.candidates("prefix_length", c, None, SimSpec.of("jaccard", "0.8"), bitmap=BitmapSpec("xor", 64), hbf_at="pre", dedup="minrank")._jdf.queryExecution().executedPlan().toString()
    assert "bit_count" in plan and "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan
