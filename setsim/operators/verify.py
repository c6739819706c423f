"""Verification of candidate pairs and the shape of results.

Verifiers: ``intersect`` (array intersection), ``merge_stop`` (sorted merge in an Arrow UDF that ends once the needed
overlap is out of reach), ``relational`` (tokens as rows, for very long sets) and ``bitset`` (bitmaps with one bit per
token of the universe: no token is read).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setsim.functions.bitmap import BitmapSpec, attach, exact_overlap
from setsim.functions.spec import SimSpec
from setsim.operators.filters import need

RESULT = "id_l long, id_r long, n_l int, n_r int, overlap int, sim double"


def attach_tokens(pairs: DataFrame, left: DataFrame, right: DataFrame, columns: tuple[str, ...] = ("toks",)) -> DataFrame:
    """Pairs with the sets' columns, suffixed per side."""
    r = left.select(F.col("sid").alias("sid_r"), *[F.col(c).alias(f"{c}_r") for c in columns])
    s = right.select(F.col("sid").alias("sid_s"), *[F.col(c).alias(f"{c}_s") for c in columns])
    return pairs.join(r, "sid_r").join(s, "sid_s")


def merge_overlap(a: np.ndarray, b: np.ndarray, required: int, i: int = 0, j: int = 0, found: int = 0) -> int:
    """Overlap of two sorted arrays from positions i and j on, or -1 as soon as ``required`` is out of reach (block-wise merge)."""
    while i < len(a) and j < len(b):
        if found + min(len(a) - i, len(b) - j) < required:
            return -1
        x, y = a[i : i + 64], b[j : j + 64]
        top = min(x[-1], y[-1])
        di, dj = int(np.searchsorted(x, top, "right")), int(np.searchsorted(y, top, "right"))
        found += len(np.intersect1d(x[:di], y[:dj], assume_unique=True))
        i, j = i + di, j + dj
    return found if found >= required else -1


def _merge_stop(batches: Iterator[tuple[pa.Array, ...]]) -> Iterator[pa.Array]:
    for left, right, required, i, j, found in batches:
        sides = [(x.offsets.to_numpy(), x.values.to_numpy(zero_copy_only=False)) for x in (left, right)]
        (at_a, flat_a), (at_b, flat_b) = sides
        out = np.empty(len(required), np.int32)
        for k, (need_, p, q, seen) in enumerate(zip(*(x.to_pylist() for x in (required, i, j, found)), strict=True)):
            out[k] = merge_overlap(flat_a[at_a[k] : at_a[k + 1]], flat_b[at_b[k] : at_b[k + 1]], need_, p, q, seen)
        yield pa.array(out)


def overlaps(pairs: DataFrame, left: DataFrame, right: DataFrame, spec: SimSpec, how: str = "intersect", universe: int | None = None) -> DataFrame:
    """``sid_r, sid_s, n_r, n_s, overlap`` of candidate pairs (pairs that a verifier gives up may be missing)."""
    base = pairs.select("sid_r", "sid_s", "n_r", "n_s")
    if how == "intersect":
        return attach_tokens(base, left, right).select("sid_r", "sid_s", "n_r", "n_s", F.size(F.array_intersect("toks_r", "toks_s")).alias("overlap"))
    if how == "merge_stop":
        # with the positions of the first common token the merge starts behind it
        placed = "pos_r" in pairs.columns and "pos_s" in pairs.columns
        wide = attach_tokens(pairs if placed else base, left, right)
        after = lambda side: F.when(F.get("toks_r", F.col("pos_r")) == F.get("toks_s", F.col("pos_s")), F.col(f"pos_{side}") + 1).otherwise(0) if placed else F.lit(0)
        seen = F.when(after("r") > 0, 1).otherwise(0)
        counted = F.arrow_udf(_merge_stop, "int")("toks_r", "toks_s", need(spec), after("r"), after("s"), seen)
        return wide.select("sid_r", "sid_s", "n_r", "n_s", counted.alias("overlap")).filter("overlap >= 0")
    if how == "relational":
        r = base.join(left.select(F.col("sid").alias("sid_r"), F.explode("toks").alias("t")), "sid_r")
        s = right.select(F.col("sid").alias("sid_s"), F.explode("toks").alias("t"))
        return r.join(s, ["sid_s", "t"]).groupBy("sid_r", "sid_s").agg(F.min("n_r").alias("n_r"), F.min("n_s").alias("n_s"), F.count("*").cast("int").alias("overlap"))
    if how == "bitset":
        if not universe:
            raise ValueError("the bitset verifier needs the number of tokens")
        bits = BitmapSpec("or", 64 * -(-universe // 64))
        wide = attach_tokens(base, attach(left, bits), attach(right, bits), tuple(bits.columns))
        return wide.select("sid_r", "sid_s", "n_r", "n_s", exact_overlap([f"{w}_r" for w in bits.columns], [f"{w}_s" for w in bits.columns]).cast("int").alias("overlap"))
    raise ValueError(f"unknown verifier {how!r}")


def finish(counted: DataFrame, spec: SimSpec, self_join: bool) -> DataFrame:
    """Accepted pairs in the result schema; in a self-join ``id_l < id_r``."""
    ok = counted.filter(spec.accepts_col("overlap", "n_r", "n_s"))
    if self_join:
        swap = F.col("sid_s") < F.col("sid_r")
        pick = lambda a, b: F.when(swap, F.col(a)).otherwise(F.col(b))
        ok = ok.select(pick("sid_s", "sid_r").alias("id_l"), pick("sid_r", "sid_s").alias("id_r"), pick("n_s", "n_r").alias("n_l"), pick("n_r", "n_s").alias("m"), "overlap")
    else:
        ok = ok.select(F.col("sid_r").alias("id_l"), F.col("sid_s").alias("id_r"), F.col("n_r").alias("n_l"), F.col("n_s").alias("m"), "overlap")
    return ok.select("id_l", "id_r", "n_l", F.col("m").alias("n_r"), "overlap", spec.sim_col("overlap", "n_l", "m").alias("sim"))
