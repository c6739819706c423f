"""Pruning rules as columns. Positions are 0-based; sides carry the suffixes ``_r`` and ``_s``."""

from __future__ import annotations

from bisect import bisect_left
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F

from setsim.functions.bitmap import BitmapSpec, hamming, overlap_bound
from setsim.functions.spec import SimSpec


def ordered(self_join: bool) -> Column:
    """Takes each unordered pair once: the smaller set (ties by id) is side s."""
    if not self_join:
        return F.lit(True)
    return (F.col("n_s") < F.col("n_r")) | ((F.col("n_s") == F.col("n_r")) & (F.col("sid_s") < F.col("sid_r")))


def length_ok(spec: SimSpec, self_join: bool) -> Column:
    """Whether the sizes admit a similar pair."""
    if self_join:
        return spec.length_ok_col("n_s", "n_r")
    small, large = F.least("n_r", "n_s"), F.greatest("n_r", "n_s")
    if spec.measure == "overlap":
        return small >= spec.num
    p, q = spec.num, spec.den
    a, b = {"jaccard": (p, q), "cosine": (p * p, q * q), "dice": (p, 2 * q - p)}[spec.measure]
    return small.cast("long") * b >= large.cast("long") * a


def need(spec: SimSpec) -> Column:
    return spec.need_col("n_r", "n_s")


def positional_ok(spec: SimSpec, pos_r: str = "pos_r", pos_s: str = "pos_s") -> Column:
    """At the first common token: it and what follows on the shorter tail must reach the needed overlap."""
    return F.least(F.col("n_r") - F.col(pos_r), F.col("n_s") - F.col(pos_s)) >= need(spec)


def suffix_bound(tail_r, tail_s, depth: int) -> int:
    """Upper bound of the overlap of two sorted tails: split both at a probe token, add the bounds of the sides."""
    if not len(tail_r) or not len(tail_s):
        return 0
    if depth <= 0:
        return min(len(tail_r), len(tail_s))
    j = len(tail_s) // 2
    probe = tail_s[j]
    i = bisect_left(tail_r, probe)
    both = int(i < len(tail_r) and tail_r[i] == probe)
    return suffix_bound(tail_r[:i], tail_s[:j], depth - 1) + both + suffix_bound(tail_r[i + both :], tail_s[j + 1 :], depth - 1)


def _split(p: Column) -> Column:
    """Two parts of a part ``(x, y, hit)``: below and above the middle token of ``y``; ``hit`` counts probes that both hold."""
    mid = F.floor(F.size(p["y"]) / 2).cast("int")
    probe = F.get(p["y"], mid)
    below, above = F.filter(p["x"], lambda t: t < probe), F.filter(p["x"], lambda t: t > probe)
    hit = F.when(F.size(p["y"]) > 0, F.size(p["x"]) - F.size(below) - F.size(above)).otherwise(0)
    part = lambda x, y, h: F.struct(x.alias("x"), y.alias("y"), h.cast("int").alias("hit"))
    return F.array(part(below, F.slice(p["y"], F.lit(1), mid), p["hit"] + hit), part(above, F.slice(p["y"], mid + 2, F.greatest(F.size(p["y"]) - mid - 1, F.lit(0))), F.lit(0)))


def suffix_ok(spec: SimSpec, depth: int = 2) -> Column:
    """On full sets with the positions of the first common token: that token and the bound of the tails behind it."""
    tail = lambda side: F.slice(f"toks_{side}", F.col(f"pos_{side}") + 2, F.greatest(F.size(f"toks_{side}") - F.col(f"pos_{side}") - 1, F.lit(0)))
    parts = F.array(F.struct(tail("r").alias("x"), tail("s").alias("y"), F.lit(0).alias("hit")))
    for _ in range(depth):
        parts = F.flatten(F.transform(parts, _split))
    bound = F.aggregate(parts, F.lit(1), lambda acc, p: acc + p["hit"] + F.least(F.size(p["x"]), F.size(p["y"])))
    return bound >= need(spec)


def _distance(batches: Iterator[tuple[pa.Array, ...]]) -> Iterator[pa.Array]:
    for columns in batches:
        words = [c.to_numpy(zero_copy_only=False).view(np.uint64) for c in columns]
        half = len(words) // 2
        yield pa.array(sum(np.bitwise_count(a ^ b).astype(np.int32) for a, b in zip(words[:half], words[half:], strict=True)), pa.int32())


def hbf_keep(spec: SimSpec, bitmap: BitmapSpec, limit: int | None, kernel: bool = False) -> Column:
    """The bitmap filter: keeps pairs above the cutoff size and pairs whose bound reaches the needed overlap."""
    left, right = [f"{w}_r" for w in bitmap.columns], [f"{w}_s" for w in bitmap.columns]
    distance = F.arrow_udf(_distance, "int")(*left, *right) if kernel else hamming(left, right)
    keep = overlap_bound("n_r", "n_s", distance) >= need(spec)
    return keep if limit is None else (F.greatest("n_r", "n_s") > limit) | keep
