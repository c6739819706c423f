"""Choices from statistics: bitmap width, prefix extension, join method.

Only statistics reach the driver: size percentiles, frequency histograms and counts over a sample of sets.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import functions as F

from setsim.functions.bitmap import BitmapSpec, choose_variant
from setsim.functions.spec import SimSpec
from setsim.functions.theory import cutoff
from setsim.operators.candidates import ell_candidates, meetings, prefix_postings, typical_prefix
from setsim.operators.order import Collection

HIT_COST, VERIFY_COST = 1.0, 20.0


def profile(sets) -> dict:
    """Sets, mean, median, 75th percentile and maximum of the sizes."""
    r = sets.agg(F.count("*").alias("sets"), F.avg("n").alias("avg"), F.expr("percentile_approx(n, 0.5)").alias("median"), F.expr("percentile_approx(n, 0.75)").alias("p75"), F.max("n").alias("max")).first()
    return r.asDict()


def choose_width(p75: int, spec: SimSpec, variant: str = "auto", most: int = 4096) -> int:
    """Least multiple of 64 bits whose cutoff covers the 75th percentile of the sizes."""
    v = choose_variant(spec) if variant == "auto" else variant
    for b in range(64, most + 1, 64):
        if cutoff(v, b, spec) >= p75:
            return b
    return most


def sampled(collection: Collection, share: int) -> Collection:
    """One in ``share`` sets, by hash of the id."""
    if share <= 1:
        return collection
    return Collection(collection.sets.filter(F.pmod(F.xxhash64("sid"), F.lit(share)) == 0), collection.vocab, 0, collection.scratch)


def choose_ell(left: Collection, right: Collection | None, spec: SimSpec, most: int = 3, sample_sets: int = 20_000) -> int:
    """Extension with the least estimated cost ``hits * HIT_COST + candidates * VERIFY_COST`` over a sample of sets."""
    count = left.sets.count()
    part = sampled(left, max(1, count // sample_sets))
    other = None if right is None else sampled(right, max(1, right.sets.count() // sample_sets))
    best, least = 1, None
    for ell in range(1, most + 1):
        own = other is None
        a = prefix_postings(part.sets, spec, ell=ell)
        b = a if own else prefix_postings(other.sets, spec, ell=ell)
        hits = meetings(a, b, spec, own).count()
        found = ell_candidates(part.sets, part.sets if own else other.sets, spec, ell, self_join=own).count()
        cost = hits * HIT_COST + found * VERIFY_COST
        if least is None or cost < least:
            best, least = ell, cost
    return best


def expected_hits(collection: Collection) -> int:
    """Upper estimate of token meetings, from the frequency histogram (before any join)."""
    r = collection.vocab.agg(F.sum((F.col("df") * (F.col("df") - 1)).cast("decimal(38,0)"))).first()[0]
    return int(r or 0) // 2


@dataclass(frozen=True)
class Plan:
    method: str
    bitmap: BitmapSpec
    dedup: str
    ell: int | str
    expected_hits: int


def plan(collection: Collection, spec: SimSpec) -> Plan:
    """Method and filter for a self-join: short prefixes use array uniqueness, few tokens longer prefixes."""
    stats = profile(collection.sets)
    bitmap = BitmapSpec("auto", min(1024, choose_width(stats["p75"] or 1, spec)))
    k = typical_prefix(collection.sets, spec)
    hits = expected_hits(collection)
    dense = hits > 50 * max(1, stats["sets"]) * max(1.0, stats["avg"] or 1)
    return Plan("ell_prefix" if dense else "prefix_length", bitmap, "array" if k <= 16 else "minrank", "adaptive" if dense else 1, hits)
