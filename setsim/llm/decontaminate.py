"""Benchmark decontamination as a prefix-filtered containment join.

A benchmark item is the set of its windows of ``window`` consecutive words. A document contains a window only if it
contains the window's rarest word, so that word alone is the join prefix (containment 1.0 needs a prefix of one
token). Words are ordered by their frequency over *all* documents. A document word that is a prefix word at window
offset q proposes the start p - q; the length and position bound is 0 <= p - q <= n_words - length; survivors are
verified word by word over exactly the window's length. The benchmark is broadcast in blocks of bounded bytes; more
blocks mean more passes whose spans are merged per document.

Defined results: null or wordless texts have no words and no hits; an item shorter than a window is one window; items
without words match nothing; an item whose id is null marks words but is not listed; repeated rows are each reported.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setsim.llm.columns import free_name, text_column

#: Lower-cases A-Z, keeps a-z, 0-9 and every byte above ASCII, turns the rest into a separator.
_FOLD = bytes(c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256))
_HITS = "struct<n_words:bigint,starts:array<int>,ends:array<int>,items:array<string>>"


def words_of(text: bytes | None) -> list[bytes]:
    """Words of a text: runs of digits, letters a-z (A-Z folded) and non-ASCII characters."""
    return text.translate(_FOLD).split() if text else []


class _Block:
    """Windows of some benchmark items over an integer vocabulary."""

    def __init__(self, items: list[tuple[str | None, bytes | None]], window: int):
        self.vocab: dict[bytes, int] = {}
        self.windows: dict[tuple[int, ...], set[str | None]] = defaultdict(set)
        for item_id, text in items:
            ids = [self.vocab.setdefault(w, len(self.vocab)) for w in words_of(text)]
            for i in range(max(1, len(ids) - window + 1) if ids else 0):
                self.windows[tuple(ids[i : i + window])].add(item_id)

    def order_by(self, counts: np.ndarray) -> None:
        """Index every window below its rarest word: word -> (offset, length) -> window -> items."""
        index: dict[int, dict[tuple[int, int], dict[bytes, list]]] = defaultdict(lambda: defaultdict(dict))
        for ids, items in self.windows.items():
            q = min(range(len(ids)), key=lambda i: (counts[ids[i]], ids[i], i))
            index[ids[q]][(q, len(ids))][np.array(ids, np.int32).tobytes()] = sorted(items, key=lambda x: (x is None, x or ""))
        self.index = {k: [(q, n, d) for (q, n), d in v.items()] for k, v in index.items()}
        self.prefix = np.zeros(len(self.vocab) + 1, bool)
        self.prefix[list(self.index)] = True
        self.windows = {}

    def encode(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.vocab.get, words, repeat(-1)), np.int32, len(words))

    def hits(self, text: bytes | None) -> dict:
        words = words_of(text)
        ids = self.encode(words)
        found: set = set()
        spans: list[tuple[int, int]] = []
        for p in np.flatnonzero(self.prefix[ids]).tolist():
            for q, n, table in self.index[int(ids[p])]:
                start = p - q
                if start >= 0 and start + n <= len(ids) and (items := table.get(ids[start : start + n].tobytes())):
                    spans.append((start, start + n))
                    found.update(items)
        merged: list[list[int]] = []
        for a, b in sorted(spans):
            if merged and a <= merged[-1][1]:
                merged[-1][1] = max(merged[-1][1], b)
            else:
                merged.append([a, b])
        return {"n_words": len(words), "starts": [a for a, _ in merged], "ends": [b for _, b in merged], "items": sorted(x for x in found if x is not None)}


def _counted(docs: DataFrame, text: str, block: _Block) -> np.ndarray:
    """Occurrences of the block's words over all documents (one partial vector per task, summed by word)."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(len(block.vocab) + 1, np.int64)
        for batch in batches:
            for t in batch.column(0):
                if (b := t.as_py()) is not None:
                    total += np.bincount(block.encode(words_of(b)) + 1, minlength=len(total))
        seen = np.flatnonzero(total[1:])
        yield pa.RecordBatch.from_arrays([pa.array(seen, pa.int32()), pa.array(total[1:][seen], pa.int64())], names=["w", "n"])

    parts = docs.select(F.col(text).cast("binary").alias("t")).mapInArrow(count, "w int, n long")
    counts = np.zeros(len(block.vocab), np.int64)
    for row in parts.groupBy("w").agg(F.sum("n").alias("n")).collect():  # at most the block's vocabulary
        counts[row.w] = row.n
    return counts


def _blocks(bench: DataFrame, item_id: str, text: str, window: int, block_bytes: int) -> Iterator[_Block]:
    rows = bench.select(F.col(item_id).cast("string").alias("i"), F.col(text).cast("binary").alias("t"))
    size = rows.agg(F.sum(F.length("t") + 64)).first()[0] or 0
    n = max(1, -(-int(size) // block_bytes))
    for k in range(n):
        part = rows if n == 1 else rows.filter(F.pmod(F.xxhash64("i", "t"), F.lit(n)) == k)
        yield _Block([(r.i, bytes(r.t) if r.t is not None else None) for r in part.collect()], window)


def benchmark_hits(docs: DataFrame, bench: DataFrame, *, text: str = "text", item_id: str = "item_id", item_text: str = "text", window: int = 10, out: str = "hits", block_bytes: int = 16 << 20) -> DataFrame:
    """All rows and columns of ``docs`` plus ``out`` (replacing a column of that name): words, merged hit spans and item ids found."""
    docs = docs.drop(out)
    names: list[str] = []
    for k, block in enumerate(_blocks(bench, item_id, item_text, window, block_bytes)):
        block.order_by(_counted(docs, text, block) if block.vocab else np.zeros(0))
        shared = docs.sparkSession.sparkContext.broadcast(block)

        def setup(shared=shared):
            block = shared.value
            return lambda texts: [block.hits(t) for t in texts]

        names.append(free_name(docs, f"__{out}_{k}"))
        docs = docs.withColumn(names[-1], text_column(setup, _HITS, text))
    if len(names) == 1:
        return docs.withColumnRenamed(names[0], out)
    spans = F.array_sort(F.concat(*[F.zip_with(f"{x}.starts", f"{x}.ends", lambda s, e: F.struct(s.alias("s"), e.alias("e"))) for x in names]))
    # two sorted spans merge where the next starts before the last ends
    merged = F.aggregate(
        spans,
        F.expr("CAST(array() AS array<struct<s:int,e:int>>)"),
        lambda acc, x: F.when((F.size(acc) > 0) & (F.element_at(acc, -1)["e"] >= x["s"]), F.concat(F.slice(acc, 1, F.greatest(F.size(acc) - 1, F.lit(0))), F.array(F.struct(F.element_at(acc, -1)["s"].alias("s"), F.greatest(F.element_at(acc, -1)["e"], x["e"]).alias("e"))))).otherwise(
            F.concat(acc, F.array(x))
        ),
    )
    items = F.array_sort(F.array_distinct(F.flatten(F.array(*[F.col(f"{x}.items") for x in names]))))
    hits = F.struct(F.col(f"{names[0]}.n_words").alias("n_words"), F.transform(merged, lambda x: x["s"]).alias("starts"), F.transform(merged, lambda x: x["e"]).alias("ends"), items.alias("items"))
    return docs.withColumn(out, hits).drop(*names)


def decontaminate(docs: DataFrame, bench: DataFrame, **options) -> DataFrame:
    """The rows of ``docs`` without any benchmark window; columns unchanged."""
    out = free_name(docs, "__contamination")
    return benchmark_hits(docs, bench, out=out, **options).filter(F.size(F.col(f"{out}.starts")) == 0).drop(out)


def op2_decontaminate(spark, sf_dir: str) -> DataFrame:
    """Contract of operator 2 over whole ``documents`` and ``benchmark``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    found = benchmark_hits(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
    hit = F.aggregate(F.zip_with("hits.starts", "hits.ends", lambda s, e: (e - s).cast("long")), F.lit(0).cast("long"), lambda acc, n: acc + n)
    return found.select("doc_id", "hits.n_words", hit.alias("n_hit"), F.size("hits.items").cast("long").alias("n_items"), F.sha2(F.concat_ws(",", "hits.items"), 256).alias("items_sha256"), (hit > 0).alias("contaminated"))
