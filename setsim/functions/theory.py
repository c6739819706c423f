"""Expected overlap bound of two random disjoint sets, the cutoff size above which a bitmap prunes little, simulation.

``expected_bound`` takes b bits and two disjoint sets of n tokens each; a pair can be expected to be pruned while the
expected bound stays below the overlap that the threshold asks of two sets of that size.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from setsim.functions.bitmap import BitmapSpec, attach, hamming, overlap_bound
from setsim.functions.spec import SimSpec


def expected_bound(variant: str, b: int, n: int) -> float:
    if variant == "or":
        q = 1 - 1 / b
        return n - b * (q**n - q ** (2 * n))
    if variant == "xor":
        return n - b / 4 * (1 - (1 - 2 / b) ** (2 * n))
    if variant == "probe":
        return min(n * n / b, n)
    raise ValueError(variant)


def expected_bound_xor_sum(b: int, n: int) -> float:
    """The xor bound by the evolution of the expected number of differing bits, token by token."""
    differing = 0.0
    for _ in range(2 * n):
        differing += (b - 2 * differing) / b
    return n - differing / 2


def cutoff(variant: str, b: int, spec: SimSpec, limit: int = 1 << 24) -> int:
    """Largest n whose expected bound does not exceed the share of n that the threshold asks (0: none)."""
    fits = lambda n: expected_bound(variant, b, n) <= spec.normalised * n
    if spec.measure == "overlap":
        fits = lambda n: expected_bound(variant, b, n) <= spec.num
    if not fits(1):
        return 0
    low, high = 1, 2
    while high < limit and fits(high):
        low, high = high, high * 2
    if high >= limit:
        return limit
    while high - low > 1:
        mid = (low + high) // 2
        low, high = (mid, high) if fits(mid) else (low, mid)
    return low


def resolve_cutoff(bitmap: BitmapSpec, spec: SimSpec) -> int | None:
    """Number of tokens above which the filter is skipped; None: never."""
    if bitmap.cutoff == "auto":
        return cutoff(bitmap.variant, bitmap.b, spec)
    return bitmap.cutoff


def cutoff_table(sizes: DataFrame, bs=(64, 256, 1024, 4096), taus=("0.5", "0.6", "0.7", "0.8", "0.9")) -> DataFrame:
    """Cutoffs per variant, width and Jaccard threshold, also relative to the width, and how many sets they cover.

    ``sizes`` is a collection's histogram ``(n, sets)``.
    """
    rows = [(v, b, t, c, c / b) for v in ("or", "xor", "probe") for b in bs for t in taus for c in [cutoff(v, b, SimSpec.of("jaccard", t))]]
    grid = sizes.sparkSession.createDataFrame(rows, "variant string, b int, tau string, cutoff int, relative double")
    met = F.broadcast(grid).crossJoin(sizes.select("n", "sets"))
    covered = met.filter("n <= cutoff").groupBy("variant", "b", "tau").agg(F.sum("sets").alias("covered"))
    return grid.join(covered, ["variant", "b", "tau"], "left").select(*grid.columns, F.coalesce("covered", F.lit(0)).cast("long").alias("covered"))


def bound_curve(sizes: DataFrame, b: int = 64) -> DataFrame:
    """Expected bound as a share of n, and the Jaccard threshold it corresponds to, at the set sizes of a collection ``(n, sets)``."""
    n = F.col("n")
    q, x = F.lit(1 - 1 / b), F.lit(1 - 2 / b)
    formulas = {"or": n - b * (F.pow(q, n) - F.pow(q, 2 * n)), "xor": n - b / 4 * (1 - F.pow(x, 2 * n)), "probe": F.least(n * n / b, n.cast("double"))}
    base = sizes.select(F.col("n").cast("int").alias("n"), "sets")
    curve = base.select("n", "sets", F.explode(F.create_map(*[c for v, f in formulas.items() for c in (F.lit(v), f / n)])).alias("variant", "share"))
    return curve.select("variant", "n", "sets", F.round("share", 9).alias("share"), F.round(F.col("share") / (2 - F.col("share")), 9).alias("jaccard"))


def simulate_bound(spark: SparkSession, variant: str, b: int = 64, n: int = 40, trials: int = 100_000, seed: int = 1) -> DataFrame:
    """Mean bound of ``trials`` pairs of disjoint random sets against the formula."""
    rows = spark.range(trials)
    for side in "rs":
        rows = rows.withColumn(f"toks_{side}", F.transform(F.sequence(F.lit(1), F.lit(n)), lambda i, side=side: F.pmod(F.xxhash64(F.col("id"), i, F.lit(f"{side}{seed}")), F.lit(1 << 30)).cast("int")))
    return mean_bound(rows, variant, b, n)


def mean_bound(rows: DataFrame, variant: str, b: int, n: int) -> DataFrame:
    """Mean bound of the pairs ``id, toks_r, toks_s`` of disjoint sets of n tokens against the formula, and how many they are."""
    spec = BitmapSpec(variant, b)
    for side in "rs":
        keep = rows.columns
        rows = attach(rows.withColumnRenamed("id", "sid"), spec, f"toks_{side}").withColumnRenamed("sid", "id")
        rows = rows.select(*keep, *[F.col(w).alias(f"{w}_{side}") for w in spec.columns])
    distance = hamming([f"{w}_r" for w in spec.columns], [f"{w}_s" for w in spec.columns])
    mean = rows.select(F.lit(n).alias("n"), distance.alias("d")).agg(F.avg(F.col("n") - F.col("d") / 2).alias("mean"), F.count("*").alias("trials"))
    want = expected_bound(variant, b, n)
    return mean.select(F.lit(variant).alias("variant"), F.lit(b).alias("b"), F.lit(n).alias("n"), "trials", "mean", F.lit(want).alias("expected"), (F.abs(F.col("mean") - want) / want).alias("relative_error"))


def row_trials(keys: DataFrame, n: int, most: int = 128, rounds: int = 4) -> DataFrame:
    """Pairs ``id, toks_r, toks_s`` of disjoint sets of n tokens from the rows of a table with keys ``(key BIGINT)``.

    Every ``2 * most`` neighbouring keys form a run; a run that is whole is cut into trials of 2n rows, and a row's token
    is a hash of its key and the round.
    """
    run = keys.filter("key IS NOT NULL").distinct().groupBy(F.floor(F.col("key") / (2 * most)).alias("run")).agg(F.sort_array(F.collect_list("key")).alias("keys"))
    cut = run.filter(F.size("keys") == 2 * most).select("run", "keys", F.explode(F.sequence(F.lit(0), F.lit(most // n - 1))).alias("part"))
    cut = cut.select("run", "keys", "part", F.explode(F.sequence(F.lit(0), F.lit(rounds - 1))).alias("round"))
    token = lambda k: F.pmod(F.xxhash64(k, F.col("round")), F.lit(1 << 30)).cast("int")
    side = lambda h: F.transform(F.slice("keys", F.col("part") * 2 * n + h * n + 1, F.lit(n)), token)
    return cut.select(F.xxhash64("run", "part", "round").alias("id"), side(0).alias("toks_r"), side(1).alias("toks_s"))


def simulation_agrees(keys: DataFrame, variant: str, b: int = 64, sizes=(4, 8, 16, 32, 64, 128), tolerance: float = 0.03) -> DataFrame:
    """Per set size: trials made of a table's rows, the expected bound, and whether the mean lies within ``tolerance`` of a set's size of it.

    Without a whole run of rows there is no trial and ``agrees`` is null.
    """
    out = None
    for n in sizes:
        one = mean_bound(row_trials(keys, n, max(sizes)), variant, b, n).select("variant", "b", "n", "trials", F.round("expected", 6).alias("expected"), (F.abs(F.col("mean") - F.col("expected")) <= tolerance * n).alias("agrees"))
        out = one if out is None else out.unionByName(one)
    return out


__all__ = ["bound_curve", "cutoff", "cutoff_table", "expected_bound", "expected_bound_xor_sum", "mean_bound", "overlap_bound", "row_trials", "resolve_cutoff", "simulate_bound", "simulation_agrees"]
