"""The experiment series: runtimes with and without the filter, ratios, precision, widths, theory."""

from __future__ import annotations

from functools import reduce
from statistics import median

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from setsim.functions.bitmap import BitmapSpec
from setsim.functions.spec import SimSpec
from setsim.operators.joins import join_collections
from setsim.operators.order import Collection
from setsim.plans import metrics
from setsim.scratch import Scratch

THRESHOLDS = ("0.5", "0.6", "0.7", "0.75", "0.8", "0.85", "0.9", "0.95")
COMPARED = {"ELL": ("ell_prefix", {"ell": 2}), "PFX-L": ("prefix_length", {}), "GRP": ("grouped_prefix", {}), "PFX-LP": ("prefix_positional", {})}
WIDTHS = (64, 128, 192, 256, 320, 512, 1024, 2048, 4096)


class Series:
    """Sums of many joins, each run and kept before the next begins: shuffle files of one of them only are on disk."""

    def __init__(self, spark: SparkSession):
        self.scratch, self.parts = Scratch(spark, "series"), []

    def add(self, sums: DataFrame) -> None:
        self.parts.append(self.scratch.save(sums, f"part{len(self.parts)}"))

    def table(self) -> DataFrame:
        return reduce(DataFrame.unionByName, self.parts)


def interleaved(forms: dict[str, object], runs: int = 3) -> dict[str, float]:
    """Median seconds per form; the forms take turns, so none always runs first."""
    took: dict[str, list[float]] = {k: [] for k in forms}
    for _ in range(runs):
        for k, make in forms.items():
            took[k].append(metrics.seconds(make, 1))
    return {k: median(v) for k, v in took.items()}


def runtimes(spark: SparkSession, inputs: dict[str, Collection], thresholds=THRESHOLDS, methods=COMPARED, bitmap: BitmapSpec | None = None, runs: int = 1) -> DataFrame:
    """Seconds of every input, method and threshold, without and with the bitmap filter."""
    rows = []
    for name, c in inputs.items():
        for t in thresholds:
            spec = SimSpec.of("jaccard", t)
            for label, (method, options) in methods.items():
                joined = lambda bits, method=method, options=options: join_collections(c, None, spec, method, bitmap=bits, **options)  # noqa: B023, E731
                took = interleaved({"orig": lambda joined=joined: joined(None), "hbf": lambda joined=joined: joined(bitmap or BitmapSpec())}, runs)
                rows.append((name, label, t, took["orig"], took["hbf"]))
    return spark.createDataFrame(rows, "input string, method string, threshold string, cost_orig double, cost_hbf double")


def result_sizes(c: Collection, thresholds=THRESHOLDS, methods=COMPARED, bitmap: BitmapSpec | None = None) -> DataFrame:
    """Pairs and summed overlap of every method, threshold and form: equal across methods and forms."""
    out = Series(c.spark)
    for t in thresholds:
        for label, (method, options) in methods.items():
            for form, bits in (("orig", None), ("hbf", bitmap or BitmapSpec())):
                joined = join_collections(c, None, SimSpec.of("jaccard", t), method, bitmap=bits, **options)
                sums = joined.agg(F.count("*").alias("pairs"), F.coalesce(F.sum("overlap"), F.lit(0)).cast("long").alias("overlap"))
                out.add(sums.select(F.lit(t).alias("threshold"), F.lit(label).alias("method"), F.lit(form).alias("form"), "pairs", "overlap"))
    return out.table()


def verified_pairs(inputs: dict[str, Collection], thresholds=("0.5", "0.8"), bitmap: BitmapSpec | None = None) -> DataFrame:
    """A table of runs whose cost is the number of pairs to verify, without and with the filter."""
    out = Series(next(iter(inputs.values())).spark)
    for name, c in inputs.items():
        for t in thresholds:
            for label, positional in (("PFX-L", False), ("PFX-LP", True)):
                one = metrics.prune_ratio(c, SimSpec.of("jaccard", t), bitmap or BitmapSpec("xor", 64, cutoff=None), positional)
                out.add(one.select(F.lit(name).alias("input"), F.lit(label).alias("method"), F.lit(t).alias("threshold"), F.col("candidates").cast("double").alias("cost_orig"), (F.col("candidates") - F.col("pruned")).cast("double").alias("cost_hbf")))
    return out.table()


def ratios(inputs: dict[str, Collection], thresholds=THRESHOLDS, bitmap: BitmapSpec | None = None) -> DataFrame:
    """Pruning ratio per input and threshold."""
    out = Series(next(iter(inputs.values())).spark)
    for name, c in inputs.items():
        for t in thresholds:
            out.add(metrics.prune_ratio(c, SimSpec.of("jaccard", t), bitmap or BitmapSpec()).withColumns({"input": F.lit(name), "threshold": F.lit(t)}))
    return out.table()


def ratios_by_shape(c: Collection, threshold: str, shapes) -> DataFrame:
    """Pruning ratio per variant and width ``(variant, b)``, without cutoff."""
    out = Series(c.spark)
    for v, b in shapes:
        out.add(metrics.prune_ratio(c, SimSpec.of("jaccard", threshold), BitmapSpec(v, b, cutoff=None)).withColumns({"variant": F.lit(v), "b": F.lit(b)}))
    return out.table()


def block_widths(spark: SparkSession, inputs: dict[str, Collection], thresholds=("0.5", "0.6", "0.7", "0.75"), widths=WIDTHS, runs: int = 1) -> DataFrame:
    """All-pairs runs per width: seconds, and the best width per input and threshold with its gain over the best prefix join."""
    rows = []
    for name, c in inputs.items():
        for t in thresholds:
            spec = SimSpec.of("jaccard", t)
            base = min(metrics.seconds(lambda m=m, o=o: join_collections(c, None, spec, m, **o), runs) for m, o in COMPARED.values())
            for b in widths:
                took = metrics.seconds(lambda: join_collections(c, None, spec, "block", bitmap=BitmapSpec("xor", b, cutoff=None)), runs)
                rows.append((name, t, b, took, base))
    table = spark.createDataFrame(rows, "input string, threshold string, b int, seconds double, baseline double")
    return table.groupBy("input", "threshold").agg(F.min_by("b", "seconds").alias("b"), F.min("seconds").alias("seconds"), F.first("baseline").alias("baseline")).withColumn("speedup", F.col("baseline") / F.col("seconds"))
