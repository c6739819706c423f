"""Hashed bitmaps of sets and the overlap bound that their Hamming distance gives.

Variants: ``or`` sets the bit of every token, ``xor`` toggles it, ``probe`` takes the next free bit circularly (all ones
once a set has as many tokens as bits). For each of them a token more changes one bit at most, so the Hamming distance
of two bitmaps never exceeds the number of unshared tokens.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from setsim.functions.spec import SimSpec

VARIANTS = ("or", "xor", "probe")
#: Thresholds of the automatic choice, on the normalised overlap.
PROBE_UPTO, XOR_FROM = 0.56, 0.73


def choose_variant(spec: SimSpec, units: str = "normalised") -> str:
    """``probe`` for low thresholds, ``xor`` for high ones, ``or`` between; ``units="literal"`` compares the threshold as it is."""
    t = spec.normalised if units == "normalised" else spec.tau
    return "probe" if t <= PROBE_UPTO else "xor" if t >= XOR_FROM else "or"


@dataclass(frozen=True)
class BitmapSpec:
    """Variant, bits (a multiple of 64, or below 64 for studies), hash (``mod`` of the id or ``xx64``) and cutoff rule."""

    variant: str = "auto"
    b: int = 64
    hash: str = "mod"
    cutoff: str | int | None = "auto"
    units: str = "normalised"

    def resolved(self, spec: SimSpec) -> BitmapSpec:
        if self.variant != "auto":
            return self
        return BitmapSpec(choose_variant(spec, self.units), self.b, self.hash, self.cutoff, self.units)

    @property
    def words(self) -> int:
        return -(-self.b // 64)

    @property
    def columns(self) -> list[str]:
        return [f"w{k}" for k in range(self.words)]


def slot(token: Column, b: int, kind: str = "mod") -> Column:
    """Bit position of a token id."""
    return F.pmod(token if kind == "mod" else F.xxhash64(token), F.lit(b)).cast("int")


def _bit(position: Column) -> Column:
    return F.call_function("shiftleft", F.lit(1).cast("long"), position.bitwiseAND(F.lit(63)))


def _probe_words(b: int, width: int):
    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for batch in batches:
            lists = batch.to_pylist()
            load = np.zeros((len(lists), b), np.int32)
            for row, slots in zip(load, lists, strict=True):
                np.add.at(row, slots or [], 1)
            carry = np.zeros(len(lists), np.int32)
            bits = np.zeros((len(lists), width * 64), np.uint8)
            for lap in range(2):  # what overflows one lap fills the next
                for k in range(b):
                    here = carry + load[:, k]
                    if lap:
                        bits[:, k] = here > 0
                    carry = np.maximum(0, here - 1)
            packed = np.packbits(bits, axis=1, bitorder="little").view(np.int64)
            yield pa.array(packed.tolist(), pa.list_(pa.int64()))

    return run


def attach(sets: DataFrame, bitmap: BitmapSpec, toks: str = "toks", sid: str = "sid") -> DataFrame:
    """``sets`` plus the bitmap's words ``w0..``; tokens are ranks in an array column."""
    names = bitmap.columns
    positions = F.transform(toks, lambda t: slot(t, bitmap.b, bitmap.hash))
    if bitmap.variant == "probe":
        words = F.arrow_udf(_probe_words(bitmap.b, bitmap.words), "array<bigint>")(positions)
        return sets.withColumn("__words", words).select(*sets.columns, *[F.element_at("__words", k + 1).alias(w) for k, w in enumerate(names)])
    if bitmap.variant not in ("or", "xor"):
        raise ValueError(f"resolve the variant first: {bitmap.variant}")
    join = (lambda a, x: a.bitwiseOR(x)) if bitmap.variant == "or" else (lambda a, x: a.bitwiseXOR(x))
    if bitmap.words <= 2:
        word = lambda k: F.aggregate(F.filter(positions, lambda p: F.shiftright(p, 6) == k), F.lit(0).cast("long"), lambda a, p: join(a, _bit(p)))
        return sets.withColumns({w: word(k) for k, w in enumerate(names)})
    # wide bitmaps: one pass over the tokens and an aggregate that combines before its shuffle
    fold = F.bit_or if bitmap.variant == "or" else F.bit_xor
    rows = sets.select(sid, F.explode(positions).alias("p"))
    wide = rows.groupBy(sid).agg(*[F.coalesce(fold(F.when(F.shiftright("p", 6) == k, _bit(F.col("p")))), F.lit(0).cast("long")).alias(w) for k, w in enumerate(names)])
    return sets.join(wide, sid, "left").select(*sets.columns, *[F.coalesce(w, F.lit(0).cast("long")).alias(w) for w in names])


def hamming(left: list[str], right: list[str]) -> Column:
    """Differing bits of two bitmaps given by their word columns."""
    return sum((F.bit_count(F.col(a).bitwiseXOR(F.col(b))) for a, b in zip(left, right, strict=True)), F.lit(0))


def overlap_bound(n: str, m: str, distance: Column) -> Column:
    """Upper bound of the overlap of sets of sizes n and m."""
    return F.floor((F.col(n) + F.col(m) - distance) / 2).cast("int")


def exact_overlap(left: list[str], right: list[str]) -> Column:
    """Overlap of two sets whose bitmaps have one bit per token of the universe."""
    return sum((F.bit_count(F.col(a).bitwiseAND(F.col(b))) for a, b in zip(left, right, strict=True)), F.lit(0))


def exact_union(left: list[str], right: list[str]) -> Column:
    return sum((F.bit_count(F.col(a).bitwiseOR(F.col(b))) for a, b in zip(left, right, strict=True)), F.lit(0))


def fold_words(columns: list[str], variant: str) -> Column:
    """The 64-bit bitmap under the ``mod`` hash of any wider ``or`` / ``xor`` bitmap."""
    out = F.col(columns[0])
    for c in columns[1:]:
        out = out.bitwiseOR(F.col(c)) if variant == "or" else out.bitwiseXOR(F.col(c))
    return out


def bit_string(columns: list[str], b: int) -> Column:
    """The bits from the highest position to the lowest."""
    return F.substring(F.concat(*[F.lpad(F.bin(c), 64, "0") for c in reversed(columns)]), 64 * len(columns) - b + 1, b)


def python_bitmap(slots: list[int], b: int, variant: str) -> int:
    """Bitmap of a list of slots as an integer, token by token."""
    bits = 0
    if variant == "probe" and len(slots) >= b:
        return (1 << b) - 1
    for s in slots:
        if variant == "or":
            bits |= 1 << s
        elif variant == "xor":
            bits ^= 1 << s
        else:
            while bits >> s & 1:
                s = (s + 1) % b
            bits |= 1 << s
    return bits
