"""Joins in cells: the same pairs and counts as the token join, whatever the blocks."""

import pytest
from pyspark.sql import functions as F

from setsim.functions.bitmap import BitmapSpec
from setsim.functions.spec import SimSpec
from setsim.operators import cells, joins
from setsim.operators.order import prepare
from setsim.plans import metrics
from tests.test_joins import _brute, _long, _rows, _sets

METHODS = [("prefix_length", {}), ("prefix_positional", {"bitmap": BitmapSpec()}), ("prefix_suffix", {}), ("ell_prefix", {"ell": 2}), ("ell_prefix", {"ell": 3, "bitmap": BitmapSpec("or", 64)}), ("block", {"bitmap": BitmapSpec("xor", 64, cutoff=None)})]


@pytest.fixture(scope="module", params=[30, 400])
def some(request, spark):
    sets = _sets(3, n=90, universe=request.param, most=40 if request.param > 64 else 14)
    return sets, prepare(_long(spark, sets))


@pytest.mark.parametrize("k,measure,threshold,room", [(0, "jaccard", "0.5", 700), (1, "jaccard", "0.8", 100_000), (2, "cosine", "0.7", 700), (3, "dice", "0.8", 700), (4, "overlap", "3", 100_000), (5, "jaccard", "0.5", 700)])
def test_cells_equal_brute_force(some, k, measure, threshold, room):
    sets, c = some
    spec = SimSpec.of(measure, threshold)
    want = _brute(sets, spec)
    for method, options in (METHODS[k], METHODS[k - 3]):
        rule = joins.in_cells(c, spec, method, cells=True, **options)
        bits = options.get("bitmap")
        base = c.sketch(joins._bitmap(spec, bits)[0]) if bits else c.sets
        got = joins.finish(cells.cell_join(base, rule, singles=c.singles, block_tokens=room), spec, True)
        assert _rows(got) == want, method


@pytest.mark.parametrize("positional", [False, True])
def test_counts_equal_token_join(some, positional):
    """Counted in the cells, candidates, pruned pairs and precision per size are those of the token join."""
    _, c = some
    spec, bits = SimSpec.of("jaccard", "0.6"), BitmapSpec("xor", 64, cutoff=None)
    rows = lambda df: sorted(tuple(r) for r in df.collect())
    assert rows(metrics.prune_ratio(c, spec, bits, positional, cells=True)) == rows(metrics.prune_ratio(c, spec, bits, positional, cells=False))
    if not positional:
        assert rows(metrics.precision_by_size(c, spec, cells=True)) == rows(metrics.precision_by_size(c, spec, cells=False))


def test_blocks_are_written_once(some, spark):
    """Every cell is a task of its own that reads its two blocks: no shuffle stands behind them, and joins share the blocks."""
    sets, c = some
    spec, made = SimSpec.of("jaccard", "0.5"), []
    kept = lambda make: made[0] if made else made.append(make()) or made[0]
    for threshold in ("0.5", "0.8"):
        spec = SimSpec.of("jaccard", threshold)
        df = cells.cell_join(c.sets, joins.in_cells(c, spec, "prefix_length", cells=True), singles=c.singles, block_tokens=700, kept=kept)
        assert "Exchange" not in df._jdf.queryExecution().executedPlan().toString()
        assert 1 < df.rdd.getNumPartitions() <= len(cells.plan(c.sets, spec, 700)[2])
        assert _rows(joins.finish(df, spec, True)) == _brute(sets, spec)
    assert all(len(files) == 1 for files in made[0].values())


def test_more_cells_than_are_read(some, monkeypatch):
    sets, c = some
    monkeypatch.setattr(cells, "READ_CELLS", 0)
    spec = SimSpec.of("jaccard", "0.5")
    df = cells.cell_join(c.sets, joins.in_cells(c, spec, "prefix_length", cells=True), singles=c.singles, block_tokens=700)
    assert "Exchange" in df._jdf.queryExecution().executedPlan().toString() and _rows(joins.finish(df, spec, True)) == _brute(sets, spec)


def test_bits_give_the_overlap(monkeypatch, spark):
    """Where at most 64 tokens exist, the overlaps counted on bits are not counted again token by token."""
    from setsim.functions.bitmap import attach

    sets = _sets(4, n=60, universe=40, most=30)
    c, spec, bits = prepare(_long(spark, sets)), SimSpec.of("jaccard", "0.5"), BitmapSpec("or", 64)
    table = attach(c.sets, bits).withColumn("block", F.lit(0)).select("block", "sid", "n", "w0", "toks")
    packed = table.mapInArrow(cells._pack(("w0",), c.singles), "block int, sid long, n int, w0 long, lo binary, hi binary").toArrow()
    block = cells.Block(packed, ("w0",))
    monkeypatch.setattr(cells, "overlap_of", None)
    found = [b for b in cells.work(block, block, cells.rule_of("prefix_length", spec, bitmap=bits), None, None)]
    got = {tuple(sorted((r["sid_r"], r["sid_s"]))): r["overlap"] for b in found for r in b.to_pylist()}
    assert got and got == {x[:2]: x[4] for x in _brute(sets, spec)}


@pytest.mark.parametrize("sent", [0, 1000])
def test_equal_sets_meet_once(sent, monkeypatch, spark):
    """A collection with many copies is joined by one set per class; pairs of members and of copies are all there, also over blocks."""
    few = _sets(5, n=30, universe=30, most=12)
    sets = [(sid + 1000 * k, toks) for k in range(9) for sid, toks in few]
    c, seen, plain = prepare(_long(spark, sets)), [], cells.cell_join
    monkeypatch.setattr(cells, "cell_join", lambda base, *a, **k: seen.append(base.count()) or plain(base, *a, **k))
    monkeypatch.setattr(joins, "SENT_MEMBERS", sent)
    monkeypatch.setattr(joins.cand, "GROUP_BLOCK", 4)
    for spec in (SimSpec.of("cosine", "0.8"), SimSpec.of("jaccard", "0.6")):
        got = joins.join_collections(c, None, spec, "prefix_length", bitmap=BitmapSpec(), cells=True)
        assert _rows(got) == _brute(sets, spec)
    assert seen == [len({frozenset(toks) for _, toks in sets})] * 2


def _block(sets, words=1):
    """A block of lists of tokens, with a bitmap of ``xor`` words."""
    import numpy as np
    import pyarrow as pa

    load = np.array([np.bincount(np.array(s) % (64 * words), minlength=64 * words) & 1 for s in sets]).astype(np.uint8)
    bits = np.packbits(load, axis=1, bitorder="little").view(np.int64)
    names = tuple(f"w{k}" for k in range(words))
    columns = {"block": pa.array([0] * len(sets), pa.int32()), "sid": pa.array(range(len(sets))), "n": pa.array([len(s) for s in sets], pa.int32())}
    columns |= {w: pa.array(bits[:, k]) for k, w in enumerate(names)} | {"toks": pa.array([sorted(s) for s in sets], pa.list_(pa.int32()))}
    return cells.Block(pa.Table.from_batches(list(cells._pack(names, 0)(iter([pa.record_batch(columns)])))), names), names


@pytest.mark.parametrize("measure,threshold,few,words", [("jaccard", "0.7", 0, 1), ("cosine", "0.8", 0, 4), ("dice", "0.6", 64, 1), ("overlap", "40", 0, 5), ("jaccard", "0.05", 0, 1)])
def test_tiles_keep_all_similar_pairs(monkeypatch, measure, threshold, few, words):
    import random

    import numpy as np

    rng = random.Random(7)
    sets = [rng.sample(range(3000), rng.randint(1, 700)) for _ in range(60)]
    sets += [list({*rng.choice(sets)[: rng.randint(1, 900)], *rng.sample(range(3000), 20)}) for _ in range(60)]
    block, names = _block(sets, words)
    spec = SimSpec.of(measure, threshold)
    for tile in ((64, 4096), (3, 7)):
        monkeypatch.setattr(cells, "TILE", tile)
        monkeypatch.setattr(cells, "FEW", few)
        found = [cells.work(block, block, cells.Rule(spec, words=names, all_pairs=True), np.zeros(3001, np.uint8), None)]
        rows = [tuple(r.values()) for batches in found for batch in batches for r in batch.to_pylist()]
        want = {(min(i, j), max(i, j), o) for i, a in enumerate(sets) for j, b in enumerate(sets[:i]) if spec.accepts(o := len({*a} & {*b}), len(a), len(b))}
        assert len(rows) == len(want) and {(min(r[:2]), max(r[:2]), r[4]) for r in rows} == want


def test_full_bitmaps_do_not_send_all_pairs_to_verification(monkeypatch):
    """Bitmaps and the guard of 512 bits say nothing of sets of 1,500 tokens; parities that fit the sizes do."""
    import random

    import numpy as np

    rng = random.Random(3)
    block, names = _block([rng.sample(range(60_000), 1500) for _ in range(80)])
    verified, overlap_of = [], cells.overlap_of
    monkeypatch.setattr(cells, "overlap_of", lambda x, y, i, j, mark: verified.append(len(i)) or overlap_of(x, y, i, j, mark))
    guard = block.parity()
    assert not list(cells.work(block, block, cells.Rule(SimSpec.of("jaccard", "0.7"), words=names, all_pairs=True), np.zeros(60_001, np.uint8), (guard, guard)))
    assert sum(verified) < 80 and block.tok.itemsize == 4
