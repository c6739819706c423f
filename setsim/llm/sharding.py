"""Sharding by histogram sort: shards of nearly equal bytes from exact counts, then one exchange.

Rows are ordered by a 126-bit key: a hash of the text (equal texts are neighbours), then a hash of the whole row and
its number, so that even a third of all rows with one text can be cut anywhere. Shard borders are found without
sorting: every round counts the exact bytes and rows between probe keys inside the borders' brackets with one
partially combined aggregation, and narrows each bracket to the cell that holds its target, until the border is within
``tolerance`` bytes or the cell holds one row.

Long rows would leave shards uneven by up to half their size. So borders are found per size class, from the largest
class down, and every class's targets fill up what the classes before have left uneven. A border table (shards x size
classes keys) is all that reaches the driver and the plan.

Slots: a shard is ``slices`` independently sorted runs (by key hash, about ``slice_rows`` rows each); a slot is the
number of rows in the runs before plus the position in the run, so no task numbers a whole shard.

Defined results: a null text counts no bytes and hashes like no text; ``size`` adds a fixed cost per row; repeated
rows are sharded row by row; an empty table gives an empty result; fewer rows than shards leave shards empty.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from setsim.scratch import Scratch

_HALF = 1 << 63
#: Lower ends of the size classes, largest first.
SIZE_CLASSES = (1 << 22, 1 << 18, 1 << 14, 1 << 11, 1 << 8, 0)
PROBES, TOLERANCE, SLICE_ROWS = 128, 16, 1_000_000


@dataclass
class _Border:
    """One border: all rows below ``lo`` are known (bytes ``below``); the target lies in ``[lo, hi)``."""

    target: float
    lo: int = 0
    hi: int = 1 << 126
    below: int = 0
    done: bool = False


def _keys(values: list[int]) -> Column:
    """Array literal of keys; constant folding makes it one object of the plan, not code per key."""
    return F.array(*[F.struct(F.lit(v // _HALF).alias("h"), F.lit(v % _HALF).alias("t")) for v in values])


def _longs(values: list[int]) -> Column:
    return F.array(*[F.lit(v).cast("long") for v in values])


def _count_at_most(values: list[int]) -> Column:
    """How many of the keys are not above the row's key."""
    key = F.struct(F.col("__h").alias("h"), F.col("__t").alias("t"))
    return F.size(F.filter(_keys(values), lambda x: x <= key)) if values else F.lit(0)


def _refine(keys: DataFrame, borders: list[_Border], probes: int, tolerance: int) -> None:
    """One counting round over the brackets of the borders that are not settled."""
    brackets = sorted({(b.lo, b.hi) for b in borders if not b.done})
    on_t, start, step = [], [], []
    for lo, hi in brackets:
        (h0, t0), (h1, t1) = divmod(lo, _HALF), divmod(hi - 1, _HALF)
        on_t.append(int(h0 == h1))
        start.append(t0 if h0 == h1 else h0)
        step.append(max(1, -(-((t1 - t0 if h0 == h1 else h1 - h0) + 1) // probes)))
    pick = lambda values: F.element_at(_longs(values), F.col("i"))
    key = F.struct(F.col("__h").alias("h"), F.col("__t").alias("t"))
    inside = keys.select("__size", "__h", "__t", key.alias("k"), _count_at_most([lo for lo, _ in brackets]).alias("i")).filter("i > 0")
    inside = inside.filter(F.col("k") <= F.element_at(_keys([hi - 1 for _, hi in brackets]), F.col("i")))
    offset = F.when(pick(on_t) == 1, F.col("__t")).otherwise(F.col("__h")) - pick(start)
    cells = inside.withColumns({"o": offset, "w": pick(step)}).selectExpr("__size", "k", "struct(i - 1 AS i, o div w AS c) AS cell")
    cells = cells.groupBy("cell.i", "cell.c").agg(F.sum("__size").alias("n"), F.count("*").alias("rows"), F.min("k").alias("lo"), F.max("k").alias("hi"))
    found: dict[int, list] = {}
    for r in cells.collect():  # at most borders x probes rows
        found.setdefault(r.i, []).append((r.lo.h * _HALF + r.lo.t, r.hi.h * _HALF + r.hi.t, int(r.n), r.rows))
    for i, bracket in enumerate(brackets):
        rows = sorted(found.get(i, []))
        for b in borders:
            if b.done or (b.lo, b.hi) != bracket:
                continue
            below = b.below
            for lo, hi, n, count in rows:
                if below + n < b.target:
                    below += n
                    continue
                if count == 1 or abs(b.target - below) <= tolerance or abs(below + n - b.target) <= tolerance or lo == hi:
                    b.done = True
                    b.lo = lo if b.target - below <= below + n - b.target else hi + 1
                else:
                    b.lo, b.hi, b.below = lo, hi + 1, below
                break
            else:
                b.done, b.lo = True, (rows[-1][1] + 1 if rows else b.lo)


def _levels(room: list[float], amount: float) -> list[float]:
    """How ``amount`` fills the lowest of the shards' levels."""
    order = sorted(room)
    level, used = order[0], 0.0
    for k, x in enumerate(order):
        if used + (x - level) * k >= amount:
            break
        used += (x - level) * k
        level = x
    else:
        k = len(order)
    level += (amount - used) / max(1, k)
    return [max(0.0, level - x) for x in room]


def borders_by_bytes(keys: DataFrame, shards: int, *, probes: int = PROBES, tolerance: int = TOLERANCE, max_rounds: int = 32) -> list[list[int]]:
    """Per size class (largest first) the ``shards - 1`` border keys."""
    filled = [0.0] * shards
    out: list[list[int]] = []
    klass = _size_class()
    totals = {r.s: int(r.n) for r in keys.groupBy(klass.alias("s")).agg(F.sum("__size").alias("n")).collect()}
    for s in range(len(SIZE_CLASSES)):
        if not totals.get(s):
            out.append([0] * (shards - 1))
            continue
        share = _levels(filled, totals[s])
        target, borders = 0.0, []
        for x in share[:-1]:
            target += x
            borders.append(_Border(target))
        part = keys.filter(klass == s)
        for _ in range(max_rounds):
            if all(b.done for b in borders):
                break
            _refine(part, borders, probes, tolerance)
        ends = []
        for b in borders:
            ends.append(max(b.lo, ends[-1] if ends else 0))
        out.append(ends)
        for r in part.groupBy(_shard_of([ends]).alias("s")).agg(F.sum("__size").alias("n")).collect():
            filled[r.s] += int(r.n)
    return out


def _size_class() -> Column:
    c = F.lit(len(SIZE_CLASSES) - 1)
    for k, low in reversed(list(enumerate(SIZE_CLASSES[:-1]))):
        c = F.when(F.col("__size") >= low, F.lit(k)).otherwise(c)
    return c


def _shard_of(borders: list[list[int]]) -> Column:
    """Shard of a row: the borders of its size class (``__class``) that are not above its key."""
    c = _count_at_most(borders[-1])
    for k, ends in reversed(list(enumerate(borders[:-1]))):
        c = F.when(F.col("__class") == k, _count_at_most(ends)).otherwise(c)
    return c


def shard_by_bytes(docs: DataFrame, shards: int, *, text: str = "text", row_bytes: int = 8, slice_rows: int = SLICE_ROWS, **search) -> DataFrame:
    """All rows and columns of ``docs`` plus ``size``, ``shard`` and ``slot`` (these replace columns of the same name)."""
    docs = docs.drop("size", "shard", "slot")
    positive = lambda c: F.shiftrightunsigned(c, 1)
    # the caller's columns travel in one struct, so no name of theirs can clash with the working columns
    size = F.coalesce(F.octet_length(F.col(text)), F.lit(0)).cast("long") + row_bytes
    hashed = [F.col(f"__source.`{c}`") for c, kind in docs.dtypes if "map<" not in kind and kind != "variant"]
    keyed = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("__source"), size.alias("__size"), positive(F.xxhash64(F.col(text))).alias("__h"), F.monotonically_increasing_id().alias("__n"))
    keyed = keyed.withColumn("__t", positive(F.xxhash64(*hashed, "__n"))).drop("__n")
    keyed = Scratch(docs.sparkSession, "sharding").save(keyed, "keyed")  # fixes the row numbers; all rounds read it
    keys = keyed.select("__size", "__h", "__t")
    borders = borders_by_bytes(keys, shards, **search)
    slices = max(1, -(-keys.count() // (shards * slice_rows)))
    placed = keyed.withColumn("__class", _size_class()).withColumn("__shard", _shard_of(borders)).withColumn("__slice", F.pmod(F.col("__t"), F.lit(slices)).cast("int"))
    counts = sorted((r[0], r[1], r[2]) for r in placed.groupBy("__shard", "__slice").count().collect())  # shards x slices rows
    before: dict[tuple[int, int], int] = {}
    total: dict[int, int] = {}
    for s, c, n in counts:
        before[s, c] = total.get(s, 0)
        total[s] = before[s, c] + n
    offsets = docs.sparkSession.createDataFrame([(s, c, n) for (s, c), n in before.items()], "__shard int, __slice int, __before long")
    run = F.row_number().over(_window())
    numbered = placed.withColumn("__row", run.cast("long") - 1).join(F.broadcast(offsets), ["__shard", "__slice"])
    return numbered.select("__source.*", F.col("__size").alias("size"), F.col("__shard").alias("shard"), (F.col("__before") + F.col("__row")).alias("slot"))


def _window():
    from pyspark.sql import Window

    return Window.partitionBy("__shard", "__slice").orderBy("__h", "__t")


def write_shards(sharded: DataFrame, path: str) -> None:
    """One folder per shard, rows in slot order within each run."""
    sharded.write.partitionBy("shard").parquet(path)


def op1_sharding(spark, sf_dir: str, shards: int = 24) -> DataFrame:
    """Contract of operator 1 over whole ``documents``: law ``bytes``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    docs = docs.withColumn("text_crc32", F.crc32(F.coalesce("text", F.lit("")).cast("binary")))
    placed = shard_by_bytes(docs, shards)
    return placed.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
