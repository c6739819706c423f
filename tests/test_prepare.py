"""What preparation leaves on disk, and its sets whatever the parts."""

from pathlib import Path

from pyspark.sql import functions as F

from setsim.operators import order
from setsim.operators.order import prepare, prepare_pair
from setsim.sources.workloads import from_arrays, long_sets
from tests.test_joins import _long, _sets


def test_spent_tables_go(spark):
    """Preparation keeps the vocabulary and the sets, not the long rows they were made of."""
    left, right = (_long(spark, _sets(k, n=20, universe=30, most=8)) for k in (1, 2))
    kept = lambda c: {p.name for p in Path(c.scratch.base.removeprefix("file://")).iterdir()}
    assert kept(prepare(left)) == {"vocab", "long_sets"}
    assert kept(prepare_pair(left, right)[0]) == {"vocab", "left_sets", "right_sets"}


def test_parts_of_the_vocabulary_give_the_same_sets(spark, monkeypatch):
    long = _long(spark, _sets(5, n=40, universe=50, most=12))
    rows = lambda c: sorted(tuple(r) for r in c.sets.select("sid", "n", F.col("toks").cast("string")).collect())
    whole = prepare(long)
    monkeypatch.setattr(order, "PART_ROWS", long.count() // 3 + 1)
    parts = prepare(long)
    assert rows(parts) == rows(whole) and {p.name for p in Path(parts.scratch.base.removeprefix("file://")).iterdir()} == {"vocab", "long_sets"}


def test_unique_ids_need_no_shuffle(spark):
    """Tokens of a row are made distinct in place where no id has two rows; ids with several rows still are one set."""
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    made = lambda rows: from_arrays(spark.createDataFrame(rows, "sid int, t array<double>"), "sid", F.col("t"))
    once, twice = made([(1, [2.0, 2.0, None]), (2, [2.0]), (None, [3.0]), (None, [3.0])]), made([(1, [2.0, 2.0]), (1, [2.0, 3.0])])
    assert "Exchange" not in plan(once) and sorted(map(tuple, once.collect())) == [(1, "2.0"), (2, "2.0")]
    assert sorted(map(tuple, twice.collect())) == [(1, "2.0"), (1, "3.0")]


def test_shared_ids_shuffle_rows_only(spark):
    """Rows of an id meet before their tokens are made: the tokens are distinct without a shuffle of their own."""
    df = spark.createDataFrame([(1, "a b b"), (1, "b c"), (2, "c"), (None, "d")], "sid int, t string")
    made = from_arrays(df, "sid", F.split("t", " "))
    plan = made._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 1 and plan.index("Generate") < plan.index("Exchange")  # the shuffle comes first: it stands below
    assert sorted(map(tuple, made.collect())) == [(1, "a"), (1, "b"), (1, "c"), (2, "c")]


def test_numbers_are_distinct_before_they_are_texts(spark):
    df = spark.createDataFrame([(1, 7), (1, 7), (1, 70), (2, None)], "sid int, t long")
    made = long_sets(df, "sid", "t")
    plan = made._jdf.queryExecution().executedPlan().toString()
    assert "tok" in plan and "string" not in plan[plan.index("Exchange") :] and sorted(map(tuple, made.collect())) == [(1, "7"), (1, "70")]
