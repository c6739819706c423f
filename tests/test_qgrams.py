"""Distinct runs of characters by the kernel: those of the expression, and no expression per character in the plan."""

import pytest
from pyspark.sql import functions as F

from setsim.functions.tokens import distinct_qgrams, qgrams
from setsim.sources.workloads import doc_q3

TEXTS = ["abcabcab", "Äß\U0001f600x\U0001f600x", "a\nb\r\n\tc", "ab", "a", "", None, "İIiı", "\u4e2d\u6587\u4e2d\u6587\x00\x7f\u0080\u07ff\u0800\uffff"]


@pytest.mark.parametrize("q", [1, 2, 3])
def test_kernel_equals_expression(spark, q):
    df = spark.createDataFrame(list(enumerate(TEXTS)), "i int, t string").repartition(2)
    for _, got, want in df.select("i", distinct_qgrams("t", q), F.coalesce(F.array_distinct(qgrams("t", q)), F.array().cast("array<string>"))).collect():
        assert sorted(got) == sorted(want)


def test_documents_use_the_kernel(spark, sf):
    assert "regexp_extract_all" not in doc_q3(spark, sf)._jdf.queryExecution().executedPlan().toString()
