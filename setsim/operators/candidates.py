"""Candidate generation: postings of prefix tokens joined on the token.

A pair meets at every token that both prefixes hold. It is reported once, at its first meeting, in one of three ways:
``array`` (each posting carries its prefix; the meeting counts only at the first common prefix token, no shuffle),
``minrank`` (an aggregation by pair with map-side combine) or ``distinct`` (for comparison). Tokens that occur in one
set only stay in sizes and prefix lengths but get no posting.

Two things keep a frequent token from meeting in one task: ``hot`` tokens are cut into blocks (one side is dealt over
them, the other sent to each), and with ``size_key`` the join key also holds a size bucket, so that postings whose sizes
rule each other out never meet (every larger set is sent to the few buckets that its smaller partners can lie in).

Every function returns ``sid_r, sid_s, n_r, n_s, pos_r, pos_s`` (positions of the first common token) and, with a
bitmap, its words per side.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setsim.functions.bitmap import BitmapSpec
from setsim.functions.spec import SimSpec
from setsim.operators.filters import hbf_keep, length_ok, need, ordered, positional_ok

ARRAY_UPTO, MEETINGS_UPTO, GROUP_BLOCK = 16, 1.5, 1000


def prefix_postings(sets: DataFrame, spec: SimSpec, *, ell: int = 1, singles: int = 0, extra: tuple[str, ...] = (), with_prefix: bool = False) -> DataFrame:
    """``rank, sid, n, pos`` (and ``extra`` columns) for every prefix token that occurs in more than one set."""
    sized = sets.withColumn("__k", spec.prefix_len_col("n", ell)).filter("__k > 0").withColumn("__p", F.slice("toks", F.lit(1), F.col("__k")))
    keep = ["sid", "n", *extra] + (["__p"] if with_prefix else [])
    posted = sized.select(*keep, F.posexplode("__p").alias("pos", "rank"))
    return posted.filter(F.col("rank") >= singles) if singles else posted


def _sides(left: DataFrame, right: DataFrame) -> tuple[DataFrame, DataFrame]:
    suffixed = lambda df, side: df.select([F.col(c).alias(f"{c}_{side}") for c in df.columns])
    return suffixed(left, "r"), suffixed(right, "s")


def _bucketed(left: DataFrame, right: DataFrame, spec: SimSpec, self_join: bool) -> tuple[DataFrame, DataFrame]:
    """Both sides with a size bucket ``z``; the left side once per bucket that admissible partners can lie in."""
    ratio = {"jaccard": spec.tau, "cosine": spec.tau**2, "dice": spec.tau / (2 - spec.tau)}[spec.measure]
    step = math.log(min(0.95, ratio))
    bucket = lambda n: F.floor(F.log(n.cast("double")) / F.lit(-step)).cast("int")  # noqa: E731  rises with n, the same on both sides
    most = F.col("n") if self_join else F.ceil(F.col("n") / ratio + 1)
    range_ = F.sequence(bucket(spec.least_partner_col("n")), bucket(most))
    return left.withColumn("z", F.explode(range_)), right.withColumn("z", bucket(F.col("n")))


def _salted(left: DataFrame, right: DataFrame, hot: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Both sides with a block ``salt`` of a frequent token; the left side once per block."""
    blocks = F.coalesce("blocks", F.lit(1))
    left, right = left.join(hot, "rank", "left"), right.join(hot, "rank", "left")
    own = F.when(blocks > 1, F.pmod(F.xxhash64("sid"), blocks)).otherwise(0).cast("int")
    return left.withColumn("salt", F.explode(F.sequence(F.lit(0), blocks - 1))).drop("blocks"), right.withColumn("salt", own).drop("blocks")


def meetings(left: DataFrame, right: DataFrame, spec: SimSpec, self_join: bool, condition=None, *, hot: DataFrame | None = None, size_key: bool = False) -> DataFrame:
    """All meetings that pass the length filter and ``condition`` (both inside the join)."""
    keys = ["rank"]
    if size_key and spec.measure != "overlap":
        left, right = _bucketed(left, right, spec, self_join)
        keys.append("z")
    if hot is not None:
        left, right = _salted(left, right, hot)
        keys.append("salt")
    r, s = _sides(left, right)
    on = ordered(self_join) & length_ok(spec, self_join)
    for k in keys:
        on = (F.col(f"{k}_r") == F.col(f"{k}_s")) & on
    return r.join(s, on if condition is None else on & condition)


def typical_prefix(sets: DataFrame, spec: SimSpec) -> int:
    """95th percentile of the prefix lengths."""
    return sets.select(spec.prefix_len_col("n").alias("k")).agg(F.expr("percentile_approx(k, 0.95)")).first()[0] or 0


def meetings_per_pair(sets: DataFrame, spec: SimSpec) -> float:
    """Estimate of how often a pair that meets does so: meetings by the frequencies of prefix tokens, dealt over all pairs."""
    counts = prefix_postings(sets, spec).groupBy("rank").agg(F.count("*").cast("double").alias("c"))
    hits = counts.agg(F.sum(F.col("c") * (F.col("c") - 1) / 2)).first()[0] or 0.0
    n = sets.count()
    load = hits / max(1.0, n * (n - 1) / 2)
    return load / -math.expm1(-load) if load > 1e-9 else 1.0


def choose_dedup(sets: DataFrame, spec: SimSpec) -> str:
    """Intersecting the prefixes of every meeting pays where prefixes are short and a pair seldom meets twice."""
    return "array" if typical_prefix(sets, spec) <= ARRAY_UPTO and meetings_per_pair(sets, spec) <= MEETINGS_UPTO else "minrank"


def prefix_candidates(left: DataFrame, right: DataFrame, spec: SimSpec, *, self_join: bool, singles: int = 0, dedup: str = "auto", positional: bool = False, bitmap: BitmapSpec | None = None, limit: int | None = None, hbf_at: str = "post", hot: DataFrame | None = None, size_key: bool = False) -> DataFrame:
    """Prefix and length filter, optionally positional filter and bitmap filter.

    The bitmap filter runs inside the join (``pre``), after uniqueness (``post``), or there in an Arrow kernel over
    whole columns of words (``kernel``).
    """
    if dedup == "auto":
        dedup = choose_dedup(left, spec)
    words = tuple(bitmap.columns) if bitmap else ()
    posted = lambda sets: prefix_postings(sets, spec, singles=singles, extra=words, with_prefix=dedup == "array")
    p = posted(left)
    pre = hbf_keep(spec, bitmap, limit) if bitmap and hbf_at == "pre" else None
    met = meetings(p, p if self_join else posted(right), spec, self_join, pre, hot=hot, size_key=size_key)
    out = ["sid_r", "sid_s", "n_r", "n_s", "pos_r", "pos_s", *[f"{w}_{side}" for side in "rs" for w in words]]
    if dedup == "array":
        once = met.filter(F.element_at(F.array_intersect("__p_r", "__p_s"), 1) == F.col("rank_r")).select(out)
    elif dedup == "minrank":
        firsts = [F.first(c).alias(c) for c in out if c.startswith("w")]
        once = met.groupBy("sid_r", "sid_s").agg(F.min("n_r").alias("n_r"), F.min("n_s").alias("n_s"), F.min("pos_r").alias("pos_r"), F.min("pos_s").alias("pos_s"), *firsts).select(out)
    elif dedup == "distinct":
        once = met.select([c for c in out if not c.startswith("pos")]).dropDuplicates(["sid_r", "sid_s"])
        once = once.withColumns({"pos_r": F.lit(0), "pos_s": F.lit(0)}).select(out)
    else:
        raise ValueError(f"unknown dedup {dedup!r}")
    if positional and dedup != "distinct":
        once = once.filter(positional_ok(spec))
    if bitmap and hbf_at in ("post", "kernel"):
        once = once.filter(hbf_keep(spec, bitmap, limit, kernel=hbf_at == "kernel"))
    return once.select(out[:6])


def ell_candidates(left: DataFrame, right: DataFrame, spec: SimSpec, ell: int, *, self_join: bool, singles: int = 0, bitmap: BitmapSpec | None = None, limit: int | None = None, hbf_levels: str = "all", hot: DataFrame | None = None, size_key: bool = False) -> DataFrame:
    """Pairs that share at least ``min(ell, need)`` tokens of their prefixes extended by ``ell - 1`` tokens."""
    words = tuple(bitmap.columns) if bitmap else ()
    posted = lambda sets: prefix_postings(sets, spec, ell=ell, singles=singles, extra=words)
    condition = None
    if bitmap:
        condition = hbf_keep(spec, bitmap, limit)
        if hbf_levels == "first":  # only meetings inside both one-token prefixes are tested
            deep = (F.col("pos_r") >= spec.prefix_len_col("n_r")) | (F.col("pos_s") >= spec.prefix_len_col("n_s"))
            condition = condition | deep
    p = posted(left)
    met = meetings(p, p if self_join else posted(right), spec, self_join, condition, hot=hot, size_key=size_key)
    pairs = met.groupBy("sid_r", "sid_s").agg(F.min("n_r").alias("n_r"), F.min("n_s").alias("n_s"), F.min("pos_r").alias("pos_r"), F.min("pos_s").alias("pos_s"), F.count("*").alias("met"))
    return pairs.filter(F.col("met") >= F.least(F.lit(ell), need(spec))).drop("met")


def prefix_groups(sets: DataFrame, spec: SimSpec, words: tuple[str, ...] = ()) -> tuple[DataFrame, DataFrame]:
    """``groups(gid, n, prefix, size)`` of sets with equal size and prefix, and ``members(gid, n, size, sid, words)``."""
    keyed = sets.withColumn("__k", spec.prefix_len_col("n")).filter("__k > 0").withColumn("prefix", F.slice("toks", F.lit(1), F.col("__k")))
    groups = keyed.groupBy("n", "prefix").agg(F.min("sid").alias("gid"), F.count("*").alias("size"))
    members = keyed.select("sid", "n", "prefix", *words).join(groups, ["n", "prefix"]).select("gid", "n", "size", "sid", *words)
    return groups, members


def group_candidates(left: DataFrame, right: DataFrame, spec: SimSpec, *, self_join: bool, singles: int = 0, dedup: str = "auto", bitmap: BitmapSpec | None = None, limit: int | None = None, hot: DataFrame | None = None, size_key: bool = False) -> DataFrame:
    """Positional prefix join of groups, expanded to their members, plus the pairs within a group.

    Members carry the bitmap's words, so the filter needs no further join. A large group's inner pairs are dealt over
    tasks in blocks of about ``GROUP_BLOCK`` members.
    """
    words = tuple(bitmap.columns) if bitmap else ()
    groups, members = prefix_groups(left, spec, words)
    as_sets = lambda g: g.select(F.col("gid").alias("sid"), "n", F.col("prefix").alias("toks"))
    others, other_members = (groups, members) if self_join else prefix_groups(right, spec, words)
    if dedup == "auto":
        dedup = choose_dedup(left, spec)
    p = lambda g: prefix_postings(as_sets(g), spec, singles=singles, with_prefix=dedup == "array")
    posted = p(groups)
    pairs = _group_pairs(posted, posted if self_join else p(others), spec, self_join, dedup, hot, size_key)
    out = ["sid_r", "sid_s", "n_r", "n_s", "pos_r", "pos_s"]
    carried = [f"{w}_{side}" for side in "rs" for w in words]
    one = lambda m, side: m.select(F.col("gid").alias(f"sid_{side}"), F.col("sid").alias(f"one_{side}"), *[F.col(w).alias(f"{w}_{side}") for w in words])
    wide = pairs.join(one(members, "r"), "sid_r").join(one(other_members, "s"), "sid_s")
    wide = wide.select(F.col("one_r").alias("sid_r"), F.col("one_s").alias("sid_s"), *out[2:], *carried)
    if self_join:
        blocks = F.ceil(F.col("size") / GROUP_BLOCK).cast("int")
        several = members.filter("size > 1")
        r = several.withColumn("block", F.explode(F.sequence(F.lit(0), blocks - 1))).select("gid", "block", F.col("sid").alias("sid_r"), F.col("n").alias("n_r"), *[F.col(w).alias(f"{w}_r") for w in words])
        s = several.withColumn("block", F.pmod(F.xxhash64("sid"), blocks).cast("int")).select("gid", "block", F.col("sid").alias("sid_s"), F.col("n").alias("n_s"), *[F.col(w).alias(f"{w}_s") for w in words])
        inner = r.join(s, ["gid", "block"]).filter("sid_s < sid_r").withColumns({"pos_r": F.lit(0), "pos_s": F.lit(0)})
        wide = wide.unionByName(inner.select(*out, *carried))
    if bitmap:
        wide = wide.filter(hbf_keep(spec, bitmap, limit))
    return wide.select(out)


def _group_pairs(p: DataFrame, q: DataFrame, spec: SimSpec, self_join: bool, dedup: str, hot: DataFrame | None, size_key: bool) -> DataFrame:
    met = meetings(p, q, spec, self_join, hot=hot, size_key=size_key)
    out = ["sid_r", "sid_s", "n_r", "n_s", "pos_r", "pos_s"]
    if dedup == "array":
        once = met.filter(F.element_at(F.array_intersect("__p_r", "__p_s"), 1) == F.col("rank_r")).select(out)
    else:
        once = met.groupBy("sid_r", "sid_s").agg(*[F.min(c).alias(c) for c in out[2:]]).select(out)
    return once.filter(positional_ok(spec))
