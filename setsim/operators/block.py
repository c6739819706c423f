"""All-pairs comparison of bitmaps in blocks, for collections or parts of them that are small enough to be quadratic.

Sets are cut into blocks by size quantile and hash. Pairs of blocks whose size ranges admit similar sets are grid cells;
a cell's two blocks of slim rows (id, size, bitmap) meet in one task, where a vectorised kernel computes all Hamming
distances in tiles and emits the pairs that the bound keeps. Tokens are read afterwards, for survivors only.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setsim.functions.bitmap import BitmapSpec
from setsim.functions.spec import SimSpec
from setsim.operators.candidates import _sides
from setsim.operators.filters import hbf_keep, length_ok, ordered

BLOCK_ROWS, TILE, MOST_SETS = 2048, 512, 2_000_000


def needed_matrix(spec: SimSpec, n: np.ndarray, m: np.ndarray) -> np.ndarray:
    """Needed overlap of all size pairs, exact."""
    a, b = n[:, None].astype(np.int64), m[None, :].astype(np.int64)
    p, q = spec.num, spec.den
    if spec.measure == "overlap":
        return np.full((len(n), len(m)), p, np.int64)
    if spec.measure == "jaccard":
        return -(-p * (a + b) // (p + q))
    if spec.measure == "dice":
        return -(-p * (a + b) // (2 * q))
    target = p * p * a * b
    o = np.floor(np.sqrt(target.astype(float)) / q).astype(np.int64) - 1
    for _ in range(3):
        o += (o * o * q * q < target) | (o < 0)
    return o


def length_matrix(spec: SimSpec, n: np.ndarray, m: np.ndarray) -> np.ndarray:
    small, large = np.minimum(n[:, None], m[None, :]).astype(np.int64), np.maximum(n[:, None], m[None, :]).astype(np.int64)
    p, q = spec.num, spec.den
    if spec.measure == "overlap":
        return small >= p
    a, b = {"jaccard": (p, q), "cosine": (p * p, q * q), "dice": (p, 2 * q - p)}[spec.measure]
    return small * b >= large * a


def kernel(spec: SimSpec, x: tuple, y: tuple, *, diagonal: bool, self_join: bool, limit: int | None, cap: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Row indices of the kept pairs of two blocks ``(ids, sizes, words)``.

    ``cap`` bounds a row's tested candidates: once a row of x has that many, its remaining pairs are kept untested.
    """
    (ids, n, w), (jds, m, v) = x, y
    out_i, out_j = [], []
    for a in range(0, len(ids), TILE):
        kept_per_row = np.zeros(min(TILE, len(ids) - a), np.int64)
        for b in range(0, len(jds), TILE):
            nn, mm = n[a : a + TILE], m[b : b + TILE]
            possible = length_matrix(spec, nn, mm)
            if self_join and diagonal:
                first = (mm[None, :] < nn[:, None]) | ((mm[None, :] == nn[:, None]) & (jds[b : b + TILE][None, :] < ids[a : a + TILE][:, None]))
                possible &= first
            if not possible.any():
                continue
            distance = np.bitwise_count(w[a : a + TILE, None, :] ^ v[None, b : b + TILE, :]).sum(2, dtype=np.int64)
            keep = (nn[:, None] + mm[None, :] - distance) // 2 >= needed_matrix(spec, nn, mm)
            if limit is not None:
                keep |= np.maximum(nn[:, None], mm[None, :]) > limit
            if cap is not None:
                keep |= (kept_per_row >= cap)[:, None]
            keep &= possible
            kept_per_row += keep.sum(1)
            i, j = np.nonzero(keep)
            out_i.append(i + a)
            out_j.append(j + b)
    return (np.concatenate(out_i), np.concatenate(out_j)) if out_i else (np.zeros(0, int), np.zeros(0, int))


def plan_cells(left: DataFrame, right: DataFrame, spec: SimSpec, self_join: bool, rows: int = BLOCK_ROWS) -> tuple[list[int], int, list[tuple[int, int]]]:
    """Size cut points, hash parts per size bucket, and the block pairs whose size ranges can match."""
    count = left.count() if self_join else max(left.count(), right.count())
    if count > MOST_SETS:
        raise ValueError(f"{count} sets are too many for an all-pairs comparison (limit {MOST_SETS}); use a prefix join")
    both = left.select("n") if self_join else left.select("n").union(right.select("n"))
    buckets = max(1, min(64, math.ceil(count / rows)))
    cuts = sorted(set(both.agg(F.percentile_approx("n", [k / buckets for k in range(1, buckets)] or [0.5])).first()[0] or [])) if buckets > 1 else []
    parts = max(1, math.ceil(count / (rows * max(1, len(cuts) + 1))))
    lows, highs = [0, *[c + 1 for c in cuts]], [*cuts, None]
    blocks = [(k, h) for k in range(len(lows)) for h in range(parts)]

    def fits(a: int, b: int) -> bool:
        small, large = (a, b) if a <= b else (b, a)
        if highs[small] is None or small == large:
            return True
        top = spec.largest_partner(highs[small])
        return top is None or top >= lows[large]

    cells = [(i, j) for i, (a, _) in enumerate(blocks) for j, (b, _) in enumerate(blocks) if (not self_join or i >= j) and fits(a, b)]
    return cuts, parts, cells


def block_candidates(left: DataFrame, right: DataFrame, spec: SimSpec, bitmap: BitmapSpec, *, self_join: bool, limit: int | None = None, cap: int | None = None, how: str = "arrow", rows: int = BLOCK_ROWS) -> DataFrame:
    """``sid_r, sid_s, n_r, n_s`` of the pairs that the bitmaps keep; both inputs carry the words."""
    words = bitmap.columns
    slim = lambda df: df.select("sid", "n", *words)
    if how == "expr":  # a nested-loop join whose condition is the filter itself
        r, s = _sides(slim(left), slim(right))
        return r.join(s, ordered(self_join) & length_ok(spec, self_join) & hbf_keep(spec, bitmap, limit)).select("sid_r", "sid_s", "n_r", "n_s")
    cuts, parts, cells = plan_cells(left, right, spec, self_join, rows)
    spark = left.sparkSession
    grid = spark.createDataFrame([(c, i, j) for c, (i, j) in enumerate(cells)], "cell int, i int, j int")
    bucket = sum(((F.col("n") > c).cast("int") for c in cuts), F.lit(0))
    block = lambda df: slim(df).withColumn("block", bucket * parts + F.pmod(F.xxhash64("sid"), F.lit(parts)).cast("int"))
    x = block(left).join(F.broadcast(grid.select("cell", F.col("i").alias("block"), (F.col("i") == F.col("j")).alias("diagonal"))), "block").withColumn("side", F.lit(0))
    y = block(right).join(F.broadcast(grid.select("cell", F.col("j").alias("block"), (F.col("i") == F.col("j")).alias("diagonal"))), "block").withColumn("side", F.lit(1))
    placed = x.unionByName(y).select("cell", "side", "diagonal", "sid", "n", *words).repartition(max(len(cells), 1), "cell").sortWithinPartitions("cell", "side")
    width = len(words)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []

        def work(table: pa.Table) -> Iterator[pa.RecordBatch]:
            side = table.column("side").to_numpy()
            ids, n = table.column("sid").to_numpy(), table.column("n").to_numpy()
            w = np.stack([table.column(c).to_numpy() for c in words], 1).view(np.uint64)
            diagonal = bool(table.column("diagonal")[0].as_py())
            a, b = side == 0, side == 1
            i, j = kernel(spec, (ids[a], n[a], w[a]), (ids[b], n[b], w[b]), diagonal=diagonal, self_join=self_join, limit=limit, cap=cap)
            left_ids, left_n, right_ids, right_n = ids[a][i], n[a][i], ids[b][j], n[b][j]
            if self_join and not diagonal:  # the larger set (ties: the larger id) is side r
                flip = (right_n > left_n) | ((right_n == left_n) & (right_ids > left_ids))
                left_ids, right_ids = np.where(flip, right_ids, left_ids), np.where(flip, left_ids, right_ids)
                left_n, right_n = np.where(flip, right_n, left_n), np.where(flip, left_n, right_n)
            for k in range(0, len(left_ids), 65_536):
                s = slice(k, k + 65_536)
                yield pa.RecordBatch.from_arrays([pa.array(left_ids[s]), pa.array(right_ids[s]), pa.array(left_n[s]), pa.array(right_n[s])], names=["sid_r", "sid_s", "n_r", "n_s"])

        def whole(last: bool) -> Iterator[pa.RecordBatch]:
            nonlocal held
            if not held:
                return
            table = pa.Table.from_batches(held)
            cell = table.column("cell").to_numpy()
            bounds = [0, *(np.flatnonzero(cell[1:] != cell[:-1]) + 1).tolist(), len(cell)]
            for a, b in zip(bounds[:-1], bounds[1:] if last else bounds[1:-1], strict=last):
                yield from work(table.slice(a, b - a))
            held = [] if last else table.slice(bounds[-2]).to_batches()

        for batch in batches:
            if batch.num_rows:
                held.append(batch)
                yield from whole(False)
        yield from whole(True)

    assert width == bitmap.words
    return placed.mapInArrow(run, "sid_r long, sid_s long, n_r int, n_s int")
