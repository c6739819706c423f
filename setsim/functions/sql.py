"""The SQL surface: functions, table functions and views of prepared collections.

``register(spark)`` adds ``sim_need(measure, p, q, n, m)``, ``sim_jaccard(a, b)``, ``hbf_bound(n, m, distance)``,
``hbf_distance(a, b)`` and the table functions ``prefix_tokens(toks, k)`` and ``slots_of(toks, b)``.
"""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from setsim.functions.bitmap import BitmapSpec, attach
from setsim.functions.spec import SimSpec
from setsim.operators.candidates import prefix_postings
from setsim.operators.order import Collection

_FUNCTIONS = {
    "sim_jaccard(a ARRAY<INT>, b ARRAY<INT>) RETURNS DOUBLE": "CAST(size(array_intersect(a, b)) AS DOUBLE) / nullif(size(array_union(a, b)), 0)",
    "sim_need(measure STRING, p BIGINT, q BIGINT, n BIGINT, m BIGINT) RETURNS BIGINT": "CASE measure WHEN 'overlap' THEN p WHEN 'jaccard' THEN (p * (n + m) + p + q - 1) div (p + q) WHEN 'dice' THEN (p * (n + m) + 2 * q - 1) div (2 * q) ELSE CAST(ceil(sqrt(CAST(p * p * n * m AS DOUBLE)) / q - 1e-9) AS BIGINT) END",
    "hbf_bound(n BIGINT, m BIGINT, distance BIGINT) RETURNS BIGINT": "(n + m - distance) div 2",
    "hbf_distance(a BIGINT, b BIGINT) RETURNS INT": "bit_count(a ^ b)",
    "expected_bound_xor(b DOUBLE, n DOUBLE) RETURNS DOUBLE": "n - b / 4 * (1 - pow(1 - 2 / b, 2 * n))",
    "expected_bound_or(b DOUBLE, n DOUBLE) RETURNS DOUBLE": "n - b * (pow(1 - 1 / b, n) - pow(1 - 1 / b, 2 * n))",
    "expected_bound_probe(b DOUBLE, n DOUBLE) RETURNS DOUBLE": "least(n * n / b, n)",
}


@F.udtf(returnType="pos: int, token: int")
class PrefixTokens:
    """The first k tokens with their positions."""

    def eval(self, toks: list, k: int):
        for i, t in enumerate((toks or [])[: k or 0]):
            yield i, t


@F.udtf(returnType="slot: int, load: int")
class SlotsOf:
    """Bit positions of a token list under the mod hash, with how many tokens each takes."""

    def eval(self, toks: list, b: int):
        loads: dict[int, int] = {}
        for t in toks or []:
            loads[t % b] = loads.get(t % b, 0) + 1
        yield from sorted(loads.items())


def register(spark: SparkSession) -> None:
    """Add the functions to the session (temporary, replacing older ones)."""
    for head, body in _FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    spark.udtf.register("prefix_tokens", PrefixTokens)
    spark.udtf.register("slots_of", SlotsOf)


def create_views(collection: Collection, name: str, spec: SimSpec, bitmap: BitmapSpec | None = None) -> None:
    """Temporary views ``sets_<name>``, ``sketch_<name>`` and ``postings_<name>``."""
    bitmap = (bitmap or BitmapSpec()).resolved(spec)
    collection.sets.createOrReplaceTempView(f"sets_{name}")
    attach(collection.sets, bitmap).createOrReplaceTempView(f"sketch_{name}")
    prefix_postings(collection.sets, spec, singles=collection.singles).createOrReplaceTempView(f"postings_{name}")
