"""Embedding near-duplicates: random-hyperplane signs in several tables, exact cosine, distributed components.

Equal vectors are collapsed into classes first, so a group of copies costs one vector. Every class gets one code of
``bits`` signs per table; classes that share a code in some table are compared by cosine in double precision. A pair
counts in the first table in which its codes agree, so link counts need no distinct pass over pairs. Buckets larger
than ``BLOCK`` are cut into blocks, and block pairs are spread over tasks: nothing is capped, and pairs never leave
the kernel, which emits per bucket one row per linked class (its number of links and one edge of a spanning forest).

``bits`` grows with the logarithm of the number of classes (buckets stay small), ``tables`` so that a pair at exactly
the threshold is missed with probability ``miss`` at most; closer pairs are missed less often.

Defined results: vectors that are null, zero, or hold null or non-finite components link with nothing and are kept;
vectors of different lengths never link; a null id is counted as a vector but is no node (its component is null and
it is not kept); repeated rows are separate vectors.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setsim.operators.components import connected_components
from setsim.scratch import Scratch

BLOCK, MISS, SEED = 512, 1e-4, 20_240_607


def plan_tables(n: int, threshold: float, miss: float = MISS) -> tuple[int, int]:
    """(bits, tables) for ``n`` vectors."""
    bits = min(30, max(4, math.ceil(math.log2(max(2, n) / 32))))
    agree = (1 - math.acos(threshold) / math.pi) ** bits
    return bits, max(1, math.ceil(math.log(miss) / math.log(1 - agree)))


def sign_codes(x: np.ndarray, bits: int, tables: int, seed: int = SEED) -> np.ndarray:
    """One code of ``bits`` signs per vector and table."""
    planes = np.random.default_rng([seed, x.shape[1]]).standard_normal((x.shape[1], bits * tables))
    signs = (x @ planes > 0).reshape(len(x), tables, bits)
    return (signs * (1 << np.arange(bits))).sum(2).astype(np.int32)


def _linked(x: np.ndarray, y: np.ndarray, threshold: float, same: bool) -> tuple[np.ndarray, np.ndarray]:
    close = x @ y.T >= threshold
    if same:
        close = np.triu(close, 1)
    return np.nonzero(close)


def _forest(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Least reachable row per row of a pair list."""
    label = np.arange(n)
    while True:
        low = np.minimum(label[a], label[b])
        before = label.copy()
        np.minimum.at(label, a, low)
        np.minimum.at(label, b, low)
        label = label[label]
        if (label == before).all():
            return label


def link_embeddings(vectors: DataFrame, *, vec_id: str = "vec_id", embedding: str = "embedding", threshold: float = 0.95, miss: float = MISS) -> DataFrame:
    """One row per vector: id, ``n_links``, ``component_id``, ``kept``."""
    spark = vectors.sparkSession
    scratch = Scratch(spark, "embeddings")
    rows = vectors.select(F.col(vec_id).alias("vec_id"), F.col(embedding).alias("e"))
    fine = F.forall("e", lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf"))) & F.exists("e", lambda v: v != 0)
    rows = rows.withColumn("e", F.when(fine, F.col("e").cast("array<double>")))
    classes = rows.filter("e IS NOT NULL").groupBy("e").agg(F.min("vec_id").alias("rep"), F.count("*").alias("n")).withColumn("cid", F.monotonically_increasing_id())
    classes = scratch.save(classes, "classes")
    bits, tables = plan_tables(classes.count(), threshold, miss)

    def code(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists = batch.column(0)
            sizes = np.array(lists.value_lengths())
            flat = lists.flatten().to_numpy(zero_copy_only=False)
            ends = sizes.cumsum()
            vec, codes = [b""] * len(sizes), [b""] * len(sizes)
            for d in np.unique(sizes):
                at = np.flatnonzero(sizes == d)
                x = np.stack([flat[ends[i] - d : ends[i]] for i in at])
                x = x / np.abs(x).max(1, keepdims=True)
                x = x / np.linalg.norm(x, axis=1, keepdims=True)
                for i, v, c in zip(at, x, sign_codes(x, bits, tables), strict=True):
                    vec[i], codes[i] = v.tobytes(), c
            flat_codes = np.concatenate(codes) if len(codes) else np.zeros(0, np.int32)
            yield pa.RecordBatch.from_arrays([batch.column(1), batch.column(2), pa.array(sizes, pa.int32()), pa.array(vec, pa.binary()), pa.ListArray.from_arrays(pa.array(np.arange(0, tables * len(sizes) + 1, tables), pa.int32()), pa.array(flat_codes, pa.int32()))], names=["cid", "n", "d", "x", "codes"])

    coded = scratch.save(classes.select("e", "cid", "n").mapInArrow(code, "cid long, n long, d int, x binary, codes array<int>"), "coded")
    spread = coded.select("cid", "n", "d", "x", "codes", F.posexplode("codes").alias("t", "c"))
    large = coded.select("d", F.posexplode("codes").alias("t", "c")).groupBy("d", "t", "c").count().filter(F.col("count") > BLOCK)
    large = scratch.save(large.select("d", "t", "c", F.ceil(F.col("count") / BLOCK).cast("int").alias("nb")), "large")
    spread = spread.join(large, ["d", "t", "c"], "left").withColumn("nb", F.coalesce("nb", F.lit(1))).withColumn("own", F.pmod(F.xxhash64("cid"), F.col("nb")).cast("int"))
    cells = spread.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("nb") - 1))).select("d", "t", "c", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "own", "cid", "n", "x", F.slice("codes", 1, F.col("t")).alias("earlier"))
    cells = cells.repartition("d", "t", "c", "i", "j").sortWithinPartitions("d", "t", "c", "i", "j")

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        kind = pa.schema([("cid", pa.int64()), ("links", pa.int64()), ("edge", pa.int64())])

        def groups(table: pa.Table, last: bool) -> tuple[list, int]:
            key = np.stack([table.column(k).to_numpy() for k in ("d", "t", "c", "i", "j")], 1)
            cut = np.flatnonzero((key[1:] != key[:-1]).any(1)) + 1
            bounds = [0, *cut.tolist(), len(key)]
            stop = len(bounds) - 1 if last else len(bounds) - 2
            done = []
            own, cid, n = (table.column(k).to_numpy() for k in ("own", "cid", "n"))
            for a, b in zip(bounds[:stop], bounds[1 : stop + 1], strict=True):
                if b - a < 2:
                    continue
                d, t, _, i, j = key[a].tolist()
                part = table.slice(a, b - a)
                x = np.frombuffer(b"".join(part.column("x").to_pylist()), np.float64).reshape(b - a, d)
                o = own[a:b]
                if i == j:
                    p, q = _linked(x, x, threshold, True)
                else:
                    left, right = np.flatnonzero(o == i), np.flatnonzero(o == j)
                    p, q = _linked(x[left], x[right], threshold, False)
                    p, q = left[p], right[q]
                if t and len(p):
                    early = part.column("earlier").combine_chunks().flatten().to_numpy().reshape(b - a, t)
                    fresh = np.ones(len(p), bool)
                    for k in range(t):
                        fresh &= early[p, k] != early[q, k]
                    p, q = p[fresh], q[fresh]
                if not len(p):
                    continue
                size = n[a:b]
                links = np.bincount(p, size[q], b - a) + np.bincount(q, size[p], b - a)
                root = _forest(b - a, p, q)
                at = np.flatnonzero(links)
                done.append((cid[a:b][at], links[at].astype(np.int64), cid[a:b][root[at]]))
            return done, bounds[stop]

        def flush(last: bool) -> pa.RecordBatch | None:
            nonlocal held
            if not held:
                return None
            table = pa.Table.from_batches(held)
            done, at = groups(table, last)
            held = table.slice(at).to_batches()
            if not done:
                return None
            return pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*done, strict=True)], schema=kind)

        for batch in batches:
            held.append(batch)
            if (out := flush(False)) is not None:
                yield out
        if (out := flush(True)) is not None:
            yield out

    found = scratch.save(cells.mapInArrow(compare, "cid long, links long, edge long"), "found")
    links = found.groupBy("cid").agg(F.sum("links").alias("links"))
    parts = connected_components(found.select(F.col("cid").alias("a"), F.col("edge").alias("b"))).withColumnsRenamed({"node": "cid"})
    info = classes.select("e", "cid", "rep", "n").join(links, "cid", "left").join(parts, "cid", "left").withColumn("component", F.coalesce("component", "cid"))
    info = scratch.save(info, "info")
    least = info.groupBy("component").agg(F.min("rep").alias("component_id"))
    info = info.join(least, "component").select("e", (F.col("n") - 1 + F.coalesce("links", F.lit(0))).alias("n_links"), "component_id")
    out = rows.join(info, "e", "left")
    node = F.when(F.col("vec_id").isNotNull(), F.coalesce("component_id", "vec_id"))
    return out.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), node.alias("component_id"), F.coalesce(F.col("vec_id") == node, F.lit(False)).alias("kept"))


def op4_embeddings(spark, sf_dir: str) -> DataFrame:
    """Contract of operator 4 over whole ``embeddings``."""
    return link_embeddings(spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "embedding"))
