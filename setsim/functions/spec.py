"""Similarity measures with exact integer thresholds.

A threshold is parsed into a reduced fraction; every bound below is integer arithmetic, because floating-point versions
of these formulas lose pairs. Each rule exists twice: on Python integers and as a Spark column.
"""

from __future__ import annotations

import math
from dataclasses import dataclass
from decimal import Decimal
from fractions import Fraction

from pyspark.sql import Column
from pyspark.sql import functions as F

MEASURES = ("overlap", "jaccard", "cosine", "dice")


def _expr(template: str, **columns: str | Column) -> Column:
    """SQL with integer division over named columns."""
    return F.expr(template.format(**columns))


def _ceil_div(a: int, b: int) -> int:
    return -(-a // b)


@dataclass(frozen=True)
class SimSpec:
    """Measure and threshold num/den (``den`` is 1 for overlap)."""

    measure: str
    num: int
    den: int = 1

    @staticmethod
    def of(measure: str, threshold: str | int | float | Decimal | Fraction) -> SimSpec:
        if measure not in MEASURES:
            raise ValueError(f"unknown measure {measure!r}: one of {MEASURES}")
        value = Fraction(str(threshold))
        if measure == "overlap":
            if value.denominator != 1 or value < 1:
                raise ValueError("an overlap threshold is a whole number of at least 1")
        elif not 0 < value <= 1:
            raise ValueError("a normalised threshold lies in (0, 1]")
        return SimSpec(measure, value.numerator, value.denominator)

    @property
    def tau(self) -> float:
        return self.num / self.den

    @property
    def normalised(self) -> float:
        """Threshold as a share of the common size of two equal-sized sets."""
        return 2 * self.tau / (1 + self.tau) if self.measure == "jaccard" else min(1.0, self.tau)

    # on integers -----------------------------------------------------------------------------------------------------

    def accepts(self, o: int, n: int, m: int) -> bool:
        p, q = self.num, self.den
        if self.measure == "overlap":
            return o >= p
        if self.measure == "jaccard":
            return o > 0 and o * q >= p * (n + m - o)
        if self.measure == "cosine":
            return o > 0 and o * o * q * q >= p * p * n * m
        return o > 0 and 2 * o * q >= p * (n + m)

    def need(self, n: int, m: int) -> int:
        """Least overlap that makes sets of sizes n and m similar."""
        p, q = self.num, self.den
        if self.measure == "overlap":
            return p
        if self.measure == "jaccard":
            return _ceil_div(p * (n + m), p + q)
        if self.measure == "cosine":
            root = math.isqrt(p * p * n * m)
            o = root // q
            while o * o * q * q < p * p * n * m:
                o += 1
            return o
        return _ceil_div(p * (n + m), 2 * q)

    def least_partner(self, n: int) -> int:
        p, q = self.num, self.den
        return {"overlap": lambda: p, "jaccard": lambda: _ceil_div(p * n, q), "cosine": lambda: _ceil_div(p * p * n, q * q), "dice": lambda: _ceil_div(p * n, 2 * q - p)}[self.measure]()

    def largest_partner(self, n: int) -> int | None:
        """None: no bound."""
        p, q = self.num, self.den
        return {"overlap": lambda: None, "jaccard": lambda: q * n // p, "cosine": lambda: q * q * n // (p * p), "dice": lambda: (2 * q - p) * n // p}[self.measure]()

    def least_overlap(self, n: int) -> int:
        """Overlap that any similar partner of a set of size n has at least."""
        return self.least_partner(n)

    def prefix_len(self, n: int, ell: int = 1) -> int:
        """Prefix in which a similar partner shows ``ell`` common tokens (or all it has), clipped to the set."""
        lo = self.least_overlap(n)
        return 0 if lo > n else max(0, min(n, n - lo + ell))

    # as columns ------------------------------------------------------------------------------------------------------

    def accepts_col(self, o: str, n: str, m: str) -> Column:
        p, q = self.num, self.den
        if self.measure == "overlap":
            return _expr(f"{{o}} >= {p}", o=o)
        if self.measure == "jaccard":
            return _expr(f"{{o}} > 0 AND {{o}} * {q}L >= {p}L * ({{n}} + {{m}} - {{o}})", o=o, n=n, m=m)
        if self.measure == "cosine":
            return _expr(f"{{o}} > 0 AND CAST({{o}} AS DECIMAL(38,0)) * {{o}} * {q * q} >= CAST({{n}} AS DECIMAL(38,0)) * {{m}} * {p * p}", o=o, n=n, m=m)
        return _expr(f"{{o}} > 0 AND 2 * {{o}} * {q}L >= {p}L * ({{n}} + {{m}})", o=o, n=n, m=m)

    def need_col(self, n: str, m: str) -> Column:
        p, q = self.num, self.den
        if self.measure == "overlap":
            return F.lit(p)
        if self.measure == "jaccard":
            return _expr(f"CAST(({p}L * ({{n}} + {{m}}) + {p + q - 1}L) div {p + q}L AS INT)", n=n, m=m)
        if self.measure == "dice":
            return _expr(f"CAST(({p}L * ({{n}} + {{m}}) + {2 * q - 1}L) div {2 * q}L AS INT)", n=n, m=m)
        # the rounded square root is off by one at most: take the least of its neighbours that suffices
        root = f"CAST(floor(sqrt(CAST({p * p}L * {n} * {m} AS DOUBLE)) / {q}) AS BIGINT)"
        holds = lambda k: f"({root} + {k}) * ({root} + {k}) * {q * q}L >= {p * p}L * {n} * {m}"
        cases = " ".join(f"WHEN {root} + {k} >= 0 AND {holds(k)} THEN {root} + {k}" for k in (-1, 0, 1))
        return F.expr(f"CAST(CASE {cases} ELSE {root} + 2 END AS INT)")

    def least_partner_col(self, n: str) -> Column:
        p, q = self.num, self.den
        if self.measure == "overlap":
            return F.lit(p)
        a, b = {"jaccard": (p, q), "cosine": (p * p, q * q), "dice": (p, 2 * q - p)}[self.measure]
        return _expr(f"CAST(({a}L * {{n}} + {b - 1}L) div {b}L AS INT)", n=n)

    def prefix_len_col(self, n: str, ell: int = 1) -> Column:
        lo = self.least_partner_col(n)
        return F.when(lo > F.col(n), F.lit(0)).otherwise(F.greatest(F.lit(0), F.least(F.col(n), F.col(n) - lo + ell))).cast("int")

    def length_ok_col(self, small: str, large: str) -> Column:
        """Whether sizes (small not above large) admit a similar pair."""
        p, q = self.num, self.den
        if self.measure == "overlap":
            return F.col(small) >= p
        a, b = {"jaccard": (p, q), "cosine": (p * p, q * q), "dice": (p, 2 * q - p)}[self.measure]
        return _expr(f"{{s}} * {b}L >= {a}L * {{l}}", s=small, l=large)

    def sim_col(self, o: str, n: str, m: str) -> Column:
        if self.measure == "overlap":
            return F.col(o).cast("double")
        if self.measure == "jaccard":
            return F.col(o).cast("double") / (F.col(n) + F.col(m) - F.col(o))
        if self.measure == "cosine":
            return F.col(o).cast("double") / F.sqrt((F.col(n).cast("bigint") * F.col(m)).cast("double"))
        return (F.col(o) * 2).cast("double") / (F.col(n) + F.col(m))
