"""Joins in shards of tokens: the same pairs as brute force, whatever the shards, from one written table."""

import pytest

from setsim.functions.bitmap import BitmapSpec
from setsim.functions.spec import SimSpec
from setsim.operators import joins, shards
from setsim.operators.order import prepare
from setsim.plans import experiments
from tests.test_joins import _brute, _long, _rows, _sets

METHODS = [("prefix_length", {}), ("prefix_positional", {}), ("ell_prefix", {"ell": 2}), ("grouped_prefix", {}), ("ell_prefix", {"ell": 3})]


@pytest.fixture(scope="module", params=[30, 400])
def some(request, spark):
    sets = _sets(3, n=90, universe=request.param, most=40 if request.param > 64 else 14)
    sets += [(len(sets) + k, s) for k, (_, s) in enumerate(sets[:25] * 2)]  # groups and classes of equal sets
    return sets, prepare(_long(spark, sets))


@pytest.mark.parametrize("measure,threshold,bits", [("jaccard", "0.5", "or"), ("jaccard", "0.95", "xor"), ("cosine", "0.7", "xor"), ("dice", "0.8", "or"), ("overlap", "3", "xor")])
def test_shards_equal_brute_force(some, monkeypatch, measure, threshold, bits):
    sets, c = some
    c.known.pop(("shards",), None)
    monkeypatch.setattr(shards, "SHARD_SETS", 150)
    monkeypatch.setattr(shards, "HITS", 40)
    spec = SimSpec.of(measure, threshold)
    want = _brute(sets, spec)
    for method, options in METHODS:
        for bitmap in (None, BitmapSpec(bits, 128 if method == "grouped_prefix" else 64)):
            got = joins.join_collections(c, None, spec, method, bitmap=bitmap, shards=True, **options)
            assert _rows(got) == want, (method, bitmap)


def test_a_series_shuffles_once(some, monkeypatch):
    """Short sets without a frequent token: all joins of a series read one table of shards, and none shuffles a pair."""
    sets, c = some
    for name, value in (("BITS", 0), ("LEAST_PAIRS", 1), ("SHARD_SETS", 150), ("cell_bytes", lambda c: 1 << 40)):
        monkeypatch.setattr(shards, name, value)
    c.known.pop(("shards",), None)
    for method, options in [("ell_prefix", {"ell": 2}), *METHODS[:2], METHODS[3]]:
        joined = joins.join_collections(c, None, SimSpec.of("jaccard", "0.5"), method, bitmap=BitmapSpec(), **options)
        assert "Exchange" not in joined._jdf.queryExecution().executedPlan().toString(), method
    assert len(c.known[("shards",)]) == 1
    found = experiments.result_sizes(c, ("0.5", "0.95")).collect()
    for t in ("0.5", "0.95"):
        want = _brute(sets, SimSpec.of("jaccard", t))
        assert {(r["pairs"], r["overlap"]) for r in found if r["threshold"] == t} == {(len(want), sum(w[4] for w in want))}
    assert len(found) == 16


def test_frequent_tokens_and_long_sets_are_left_alone(some, monkeypatch):
    _, c = some
    rule = joins.in_shards(c, SimSpec.of("jaccard", "0.8"), "prefix_length", shards=True)
    assert rule and not shards.pays(c, rule)  # few meetings
    for name, value in (("BITS", 0), ("LEAST_PAIRS", 1), ("cell_bytes", lambda c: 1 << 40)):
        monkeypatch.setattr(shards, name, value)
    assert shards.pays(c, rule)
    monkeypatch.setattr(shards, "MOST_DF", 1)
    assert not shards.pays(c, rule)
    assert joins.in_shards(c, SimSpec.of("jaccard", "0.8"), "prefix_length", shards=True, size_key=True) is None
