"""Cost and accuracy measures of joins."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, Observation, Window
from pyspark.sql import functions as F

from setsim.functions.bitmap import BitmapSpec, hamming
from setsim.functions.spec import SimSpec
from setsim.functions.theory import resolve_cutoff
from setsim.operators.candidates import choose_dedup, meetings, prefix_candidates, prefix_postings
from setsim.operators.filters import hbf_keep
from setsim.operators.cells import blocks_key, cell_join
from setsim.operators.joins import in_cells, join_collections, naive
from setsim.operators.order import Collection
from setsim.operators.verify import attach_tokens, overlaps


def seconds(make: Callable[[], DataFrame], runs: int = 5) -> float:
    """Mean seconds of ``runs`` full evaluations into a sink that drops the rows."""
    took = 0.0
    for _ in range(runs):
        began = time.perf_counter()
        make().write.format("noop").mode("overwrite").save()
        took += time.perf_counter() - began
    return took / runs


def collection_profile(long: DataFrame) -> DataFrame:
    """Sets, largest, mean and median size, distinct tokens of long sets."""
    sizes = long.groupBy("sid").agg(F.count("*").alias("n"))
    stats = sizes.agg(F.count("*").alias("sets"), F.max("n").alias("max_n"), F.round(F.avg("n"), 6).alias("avg_n"), F.percentile("n", F.lit(0.5)).alias("median_n"))
    return stats.join(long.agg(F.countDistinct("tok").alias("tokens")))


def size_histogram(long: DataFrame) -> DataFrame:
    return long.groupBy("sid").agg(F.count("*").alias("n")).groupBy("n").agg(F.count("*").alias("sets"))


def token_histogram(long: DataFrame) -> DataFrame:
    """How many tokens occur in how many sets."""
    return long.groupBy("tok").agg(F.count("*").alias("df")).groupBy("df").agg(F.count("*").alias("tokens"))


def tested_candidates(collection: Collection, spec: SimSpec, bitmap: BitmapSpec, positional: bool = False) -> DataFrame:
    """Unique prefix-and-length (and positional) candidates with ``kept``: whether the bitmap filter lets them pass."""
    bitmap = bitmap.resolved(spec)
    dedup = collection.once(("dedup", spec), lambda: choose_dedup(collection.sets, spec))
    found = prefix_candidates(collection.sets, collection.sets, spec, self_join=True, singles=collection.singles, dedup=dedup, positional=positional, hot=collection.hot())
    marked = attach_tokens(found, a := collection.sketch(bitmap), a, tuple(bitmap.columns))
    return marked.select("sid_r", "sid_s", "n_r", "n_s", hbf_keep(spec, bitmap, resolve_cutoff(bitmap, spec)).alias("kept"))


def counts_in_cells(collection: Collection, spec: SimSpec, bitmap: BitmapSpec, positional: bool = False, verify: bool = False, cells: bool | str = "auto") -> DataFrame | None:
    """``n, candidates, kept, similar`` per size of the larger set, counted where the candidates arise; None where a token join writes less."""
    bitmap = bitmap.resolved(spec)
    rule = in_cells(collection, spec, "prefix_positional" if positional else "prefix_length", bitmap=bitmap, cells=cells)
    if rule is None:
        return None
    rule = replace(rule, limit=resolve_cutoff(bitmap, spec), counts=True, verify=verify)
    kept = lambda make: collection.once(blocks_key(bitmap), make)
    return cell_join(collection.cell_sets(bitmap), rule, singles=collection.singles, kept=kept).groupBy("n").agg(*[F.sum(c).alias(c) for c in ("candidates", "kept", "similar")])


def prune_ratio(collection: Collection, spec: SimSpec, bitmap: BitmapSpec, positional: bool = False, cells: bool | str = "auto") -> DataFrame:
    """Candidates, pruned ones and their share."""
    counted = counts_in_cells(collection, spec, bitmap, positional, cells=cells)
    if counted is not None:
        total = lambda c: F.coalesce(F.sum(c), F.lit(0)).cast("long")
        return counted.agg(total("candidates").alias("candidates"), total(F.col("candidates") - F.col("kept")).alias("pruned")).withColumn("ratio", F.round(F.try_divide("pruned", "candidates"), 6))
    return tested_candidates(collection, spec, bitmap, positional).agg(F.count("*").alias("candidates"), F.count_if(~F.col("kept")).alias("pruned")).withColumn("ratio", F.round(F.try_divide("pruned", "candidates"), 6))


def variant_distance(collection: Collection, b: int = 64, first: str = "or", second: str = "xor") -> DataFrame:
    """Mean number of bits in which two variants' bitmaps of one set differ, by set size."""
    one, other = collection.sketch(BitmapSpec(first, b)), collection.sketch(BitmapSpec(second, b))
    words = BitmapSpec(first, b).columns
    both = one.select("sid", "n", *[F.col(w).alias(f"{w}_r") for w in words]).join(other.select("sid", *[F.col(w).alias(f"{w}_s") for w in words]), "sid")
    apart = hamming([f"{w}_r" for w in words], [f"{w}_s" for w in words])
    return both.groupBy("n").agg(F.count("*").alias("sets"), F.round(F.avg(apart), 6).alias("bits"))


def naive_tests(collection: Collection) -> DataFrame:
    """Pairs of sets that a join without filters verifies."""
    return collection.sets.agg(F.count("*").alias("sets")).withColumn("tests", F.expr("sets * (sets - 1) div 2"))


def prune_ratio_by_variant(collection: Collection, spec: SimSpec, b: int = 64, variants=("or", "xor", "probe")) -> DataFrame:
    """Pruning ratio per variant without cutoff."""
    out = None
    for v in variants:
        one = prune_ratio(collection, spec, BitmapSpec(v, b, cutoff=None)).withColumn("variant", F.lit(v))
        out = one if out is None else out.unionByName(one)
    return out.select("variant", "candidates", "pruned", "ratio")


def precision_by_size(collection: Collection, spec: SimSpec, b: int = 64, variant: str = "xor", cells: bool | str = "auto") -> DataFrame:
    """Share of similar pairs among those the filter keeps, by the size of the larger set (no cutoff)."""
    counted = counts_in_cells(collection, spec, BitmapSpec(variant, b, cutoff=None), verify=True, cells=cells)
    if counted is not None:
        return counted.filter("kept > 0").select("n", F.col("kept").alias("unpruned"), "similar", F.round(F.col("similar") / F.col("kept"), 6).alias("precision"))
    kept = tested_candidates(collection, spec, BitmapSpec(variant, b, cutoff=None)).filter("kept")
    checked = overlaps(kept, collection.sets, collection.sets, spec).select("n_r", spec.accepts_col("overlap", "n_r", "n_s").alias("similar"))
    per = checked.groupBy("n_r").agg(F.count("*").alias("unpruned"), F.count_if(F.col("similar")).alias("similar"))
    return per.select(F.col("n_r").alias("n"), "unpruned", "similar", F.round(F.col("similar") / F.col("unpruned"), 6).alias("precision"))


def lost_pairs(collection: Collection, spec: SimSpec, method: str, **options) -> DataFrame:
    """Similar pairs that a method misses (must be empty: recall is 1)."""
    return naive(collection, None, spec).join(join_collections(collection, None, spec, method, **options), ["id_l", "id_r"], "left_anti")


def stage_counts(collection: Collection, spec: SimSpec, bitmap: BitmapSpec, dedup: str = "auto") -> DataFrame:
    """One row: index hits, unique candidates, bitmap tests, pruned, verified, similar. Two runs, counted while they run."""
    spark = collection.spark
    bitmap = bitmap.resolved(spec)
    limit = resolve_cutoff(bitmap, spec)
    if dedup == "auto":
        dedup = choose_dedup(collection.sets, spec)
    p = prefix_postings(collection.sets, spec, singles=collection.singles)
    hits = meetings(p, p, spec, True).count()
    tested = F.lit(True) if limit is None else F.greatest("n_r", "n_s") <= limit
    seen, passed = Observation(), Observation()
    marked = tested_candidates(collection, spec, bitmap).observe(seen, F.count("*").alias("candidates"), F.count_if(tested).alias("tests"), F.count_if(~F.col("kept")).alias("pruned"))
    checked = overlaps(marked.filter("kept"), collection.sets, collection.sets, spec).observe(passed, F.count("*").alias("verified"))
    similar = checked.filter(spec.accepts_col("overlap", "n_r", "n_s")).count()
    a, b = seen.get, passed.get
    row = (hits, a["candidates"], a["tests"], a["pruned"], b["verified"], similar)
    return spark.createDataFrame([row], "hits long, candidates long, tests long, pruned long, verified long, similar long")


# measures over a table of runs (input, method, threshold, cost_orig, cost_hbf); a cost is seconds, or pairs to verify -----------


def improvement(runs: DataFrame) -> DataFrame:
    """Speed-up and percentage gained by the filter, per run."""
    return runs.withColumns({"speedup": F.col("cost_orig") / F.col("cost_hbf"), "improvement": (F.col("cost_orig") / F.col("cost_hbf") - 1) * 100})


def mean_improvement(runs: DataFrame) -> DataFrame:
    """Means per method and threshold, per input and threshold, and over all (grouping sets)."""
    cube = improvement(runs).groupingSets([["method", "threshold"], ["input", "threshold"], []], "method", "input", "threshold")
    return cube.agg(F.round(F.avg("improvement"), 6).alias("mean_improvement"), F.count("*").alias("runs"))


def by_threshold(means: DataFrame, key: str) -> DataFrame:
    """One column per threshold."""
    return means.filter(F.col(key).isNotNull() & F.col("threshold").isNotNull()).groupBy(key).pivot("threshold").agg(F.first("mean_improvement"))


def totals(runs: DataFrame) -> DataFrame:
    """Cost with and without filter per method and the percentage saved."""
    sums = runs.groupBy("method").agg(F.sum("cost_orig").alias("orig"), F.sum("cost_hbf").alias("hbf"))
    return sums.withColumn("saved", F.round((1 - F.col("hbf") / F.col("orig")) * 100, 6))


def wins(runs: DataFrame) -> DataFrame:
    """How often each method is fastest on an input and threshold: among originals, among filtered, among all."""
    long = runs.select("input", "threshold", "method", F.explode(F.array(F.struct(F.lit("orig").alias("form"), F.col("cost_orig").alias("s")), F.struct(F.lit("hbf").alias("form"), F.col("cost_hbf").alias("s")))).alias("x")).select("input", "threshold", "method", "x.form", "x.s")
    place = lambda *extra: F.rank().over(Window.partitionBy("input", "threshold", *extra).orderBy("s"))
    ranked = long.withColumns({"in_form": place("form"), "overall": place()})
    return ranked.groupBy("method", "form").agg(F.count_if(F.col("in_form") == 1).alias("wins_in_form"), F.count_if(F.col("overall") == 1).alias("wins_overall"))


def share_improved(runs: DataFrame) -> DataFrame:
    """Share of runs that the filter makes faster, and of inputs whose fastest run uses it."""
    per_run = runs.agg(F.round(F.avg((F.col("cost_hbf") < F.col("cost_orig")).cast("double")), 6).alias("runs_improved"))
    best = runs.groupBy("input", "threshold").agg(F.min("cost_orig").alias("o"), F.min("cost_hbf").alias("h"))
    return per_run.join(best.agg(F.round(F.avg((F.col("h") < F.col("o")).cast("double")), 6).alias("inputs_improved")))
