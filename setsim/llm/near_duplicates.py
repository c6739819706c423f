"""N-gram Jaccard join by partition-and-enumerate signatures.

A document is the set of its distinct word shingles (hashed to 64 bits). Two sets of sizes a and b whose Jaccard
similarity reaches p/q differ in at most (a + b)(q - p) div (q + p) elements.

*Size classes.* Class j holds the sizes from 2^j to 2^(j+1) - 1. A pair is looked for in the class of its larger set, so
a set belongs to its own class and, if a similar larger set can lie in the next one, to that class too.

*Partition and enumeration.* A class cuts the feature domain into parts by hash, and each part into ``SUBPARTS``. At
most floor(delta / 2) parts can hold two or more differing elements; in any other part all but one of the three
subparts agree. So a set enumerates, part by part, the subsets of two subparts and hashes their content, until it
has passed floor(delta / 2) + 1 *full* parts (parts in which at least two subparts hold elements: there every subset
has content). The set that stops first has one full part more than can be spoilt, hence a similar pair shares a
signature with content. A set that runs out of parts before has too few elements for that and also emits its empty
subsets; of two such sets, both do.

*Frequent elements.* Shingles of passages that many documents share would fill buckets with documents that have nothing
else in common. One pass over all texts finds them (at least ``HOT_RATE`` of the documents of a batch, at most
``HOT_MOST`` of them, the most frequent first). Signatures are enumerated on the other elements; a set that is short of
full parts without the frequent ones adds the signatures of all its elements. The argument above holds for either
element set alone, so which elements are called frequent decides about cost, never about results.

*Groups.* In a bucket of equal signatures every document is first compared with one pivot, the least id: a group of
m copies costs m comparisons. Only then, and only between documents that are not yet connected, the other pairs of
a bucket are compared, so that no link between components is lost. Pairs inside a component are never made.

*Bitmaps.* Every set also gets a parity bitmap of ``64 * BITMAP`` bits. The Hamming distance of two bitmaps is at most
the number of differing elements, which bounds the overlap from above; pairs that the bound rules out (documents that
share a frequent passage and little else) end inside the join that proposes them.

All other candidates are verified on the exact sets. Defined results: null texts and texts without words have no shingles and
link with nothing; a text of fewer words than a shingle is one shingle; rows of one id are one node; a null id links
with nothing and has no component.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setsim.llm.columns import text_slices
from setsim.operators.components import connected_components
from setsim.scratch import Scratch

WORDS, NUM, DEN, SUBPARTS, BITMAP = 5, 4, 5, 3, 8
HOT_RATE, HOT_MOST, BROADCAST_ROWS = 0.002, 500_000, 500_000
_BITS = [f"w{k}" for k in range(BITMAP)]
_ODD = [np.uint64(x | 1) for x in np.random.default_rng(7).integers(1 << 62, 1 << 63, 64, dtype=np.uint64).tolist()]


def _mix(h: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit integers that spreads every bit."""
    h = (h ^ (h >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15)
    h = (h ^ (h >> np.uint64(29))) * np.uint64(0xD6E8FEB86659FD93)
    return h ^ (h >> np.uint64(32))


def shingle_sets(texts: list[bytes | None], words: int = WORDS) -> list[np.ndarray]:
    """Sorted distinct 64-bit shingle hashes per text; words are runs without ASCII white space, A-Z folded."""
    split = [t.lower().split() if t else [] for t in texts]
    sizes = [len(w) for w in split]
    h = np.fromiter(map(xxhash.xxh3_64_intdigest, chain.from_iterable(split)), np.uint64, sum(sizes))
    rolled = np.zeros(len(h), np.uint64)
    for k in range(min(words, len(h))):
        rolled[: len(h) - k] += h[k:] * _ODD[k]
    rolled = _mix(rolled)
    out, at = [], 0
    for n in sizes:
        if n >= words:
            out.append(np.unique(rolled[at : at + n - words + 1]))
        else:
            out.append(_mix((h[at : at + n] * np.array(_ODD[:n], np.uint64)).sum(keepdims=True) + np.uint64(n)) if n else np.zeros(0, np.uint64))
        at += n
    return out


def set_keys(sets: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Two 64-bit sums that identify a set."""
    a = np.array([_mix(s).sum() if len(s) else 0 for s in sets], np.uint64)
    b = np.array([_mix(s ^ _ODD[40]).sum() if len(s) else 0 for s in sets], np.uint64)
    return a.view(np.int64), b.view(np.int64)


def bitmaps(sets: list[np.ndarray]) -> np.ndarray:
    """Parity of the elements per bit position, as 64-bit words."""
    out = np.zeros((len(sets), BITMAP * 8), np.uint8)
    for row, s in zip(out, sets, strict=True):
        row[:] = np.packbits(np.bincount((s % np.uint64(64 * BITMAP)).astype(np.int64), minlength=64 * BITMAP) & 1)
    return out.view(np.int64)


def can_be_similar(num: int, den: int):
    """Condition on columns ``na, wa0.., nb, wb0..``: sizes and bitmaps allow the pair."""
    apart = sum((F.bit_count(F.col(f"{w}a").bitwiseXOR(F.col(f"{w}b"))) for w in _BITS), F.lit(0))
    sizes = (F.least("na", "nb") * den >= F.greatest("na", "nb") * num)
    return sizes & ((F.col("na") + F.col("nb") - apart) * (num + den) >= (F.col("na") + F.col("nb")) * (2 * num))


def max_difference(a: int, b: int, num: int = NUM, den: int = DEN) -> int:
    """Most elements in which sets of sizes a and b may differ at Jaccard num/den."""
    return (a + b) * (den - num) // (den + num)


def classes_of(n: int, num: int = NUM, den: int = DEN) -> list[tuple[int, int]]:
    """(size class, largest difference to a similar set in that class) of a set of n elements."""
    j = n.bit_length() - 1
    top, largest = (2 << j) - 1, n * den // num
    out = [(j, max_difference(n, min(top, largest), num, den))]
    if largest > top:
        out.append((j + 1, max_difference(n, largest, num, den)))
    return [(c, d) for c, d in out if d]


def parts_of(j: int, num: int = NUM, den: int = DEN) -> int:
    """Parts of size class j: what its largest set needs, and some more against parts that are not full."""
    need = max_difference((2 << j) - 1, (2 << j) - 1, num, den) // 2 + 1
    return need + need // 8


def _enumerate(h: np.ndarray, j: int, delta: int, parts: int, kind: int, empties: bool) -> tuple[list[np.ndarray], bool]:
    """Signatures of one element set in size class j, and whether it had full parts enough."""
    spread = _mix(h + _ODD[41 + kind])
    cell = ((spread >> np.uint64(32)) % np.uint64(parts) * np.uint64(SUBPARTS) + ((spread & np.uint64(0xFFFFFFFF)) * np.uint64(SUBPARTS) >> np.uint64(32))).astype(np.int64)
    content = _mix(h + _ODD[43 + kind])
    held = np.bincount(cell, minlength=parts * SUBPARTS).reshape(parts, SUBPARTS) > 0
    low, high = (np.bincount(cell, x.astype(np.float64), parts * SUBPARTS).astype(np.uint64) for x in (content & np.uint64(0xFFFFFFFF), content >> np.uint64(32)))
    sums = (low + (high << np.uint64(32))).reshape(parts, SUBPARTS)
    passed = (held.sum(1) >= 2).cumsum()
    enough = bool(passed[-1] > delta // 2)
    stop = int(np.searchsorted(passed, delta // 2 + 1)) + 1 if enough else parts
    out = []
    for i, k in ((0, 1), (0, 2), (1, 2)):
        salt = np.arange(stop, dtype=np.uint64) * np.uint64(512) + np.uint64(j * 8 + kind * 4 + i + k)
        sig = _mix(_mix(sums[:stop, i] * _ODD[45] + sums[:stop, k] * _ODD[46]) + salt * _ODD[47])
        out.append(sig[held[:stop, i] | held[:stop, k]] if enough or not empties else sig)
    return out, enough


def signatures(h: np.ndarray, hot: np.ndarray | None = None, num: int = NUM, den: int = DEN) -> np.ndarray:
    """Signatures of one set; ``hot`` are the sorted frequent elements."""
    out: list[np.ndarray] = []
    rare = h
    if hot is not None and len(hot):
        at = np.minimum(np.searchsorted(hot, h), len(hot) - 1)
        rare = h[hot[at] != h]
    for j, delta in classes_of(len(h), num, den):
        parts = parts_of(j, num, den)
        found, enough = _enumerate(rare, j, delta, parts, 0, False)
        out += found
        if not enough:
            out += _enumerate(h, j, delta, parts, 1, True)[0]
    return np.concatenate(out) if out else np.zeros(0, np.uint64)


def _batches(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.RecordBatch, list[np.ndarray]]]:
    for batch in batches:
        for part, texts in text_slices(batch, 1, limit=4 << 20):
            yield part, shingle_sets(texts)


def _keyed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch, sets in _batches(batches):
        k1, k2 = set_keys(sets)
        bits = bitmaps(sets)
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([len(s) for s in sets], pa.int64()), pa.array(k1), pa.array(k2), *(pa.array(bits[:, k]) for k in range(BITMAP))], names=["doc_id", "n", "k1", "k2", *_BITS])


def _frequent(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch, sets in _batches(batches):
        every, counts = np.unique(np.concatenate(sets), return_counts=True)
        keep = counts >= max(4, HOT_RATE * len(sets))
        yield pa.RecordBatch.from_arrays([pa.array(every[keep].view(np.int64)), pa.array(counts[keep].astype(np.int64))], names=["h", "n"])


def _signed(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        hot = shared.value
        for batch, sets in _batches(batches):
            k1, _ = set_keys(sets)
            ids = batch.column(0).to_numpy()
            sigs, owners = [], []
            for doc_id, s, k in zip(ids, sets, k1.tolist(), strict=True):
                if k in seen or not len(s):  # a copy within this task has the same signatures; its class has one member here
                    continue
                if len(seen) > 200_000:
                    seen.clear()
                seen.add(k)
                sig = signatures(s, hot)
                sigs.append(sig)
                owners.append(np.full(len(sig), doc_id, np.int64))
            if sigs:
                sig, owner = np.concatenate(sigs).view(np.int64), np.concatenate(owners)
                for a in range(0, len(sig), 65_536):
                    yield pa.RecordBatch.from_arrays([pa.array(sig[a : a + 65_536]), pa.array(owner[a : a + 65_536])], names=["sig", "id"])

    return run


def _stars(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """From rows sorted by (sig, id): every member of a bucket with the bucket's first id."""
    last_sig = last_pivot = None
    for batch in batches:
        sig, ids = batch.column(0).to_numpy(), batch.column(1).to_numpy()
        if not len(sig):
            continue
        fresh = np.empty(len(sig), bool)
        fresh[1:] = sig[1:] != sig[:-1]
        fresh[0] = sig[0] != last_sig
        start = np.maximum.accumulate(np.where(fresh, np.arange(len(sig)), -1))
        pivot = np.where(start >= 0, ids[start], last_pivot if last_pivot is not None else 0)
        keep = pivot != ids
        if keep.any():
            yield pa.RecordBatch.from_arrays([pa.array(sig[keep]), pa.array(ids[keep]), pa.array(pivot[keep].astype(np.int64))], names=["sig", "id", "pivot"])
        last_sig, last_pivot = sig[-1], int(pivot[-1])


def _sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch, sets in _batches(batches):
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([s.tobytes() for s in sets], pa.binary())], names=["id", "elements"])


def _verify(num: int, den: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for x, y in zip(batch.column(2), batch.column(3), strict=True):
                a, b = (np.frombuffer(v.as_buffer(), np.uint64) for v in (x, y))
                both = len(a) + len(b)
                if min(len(a), len(b)) * den < max(len(a), len(b)) * num:
                    keep.append(False)
                    continue
                merged = np.concatenate([a, b])
                merged.sort(kind="stable")
                shared = int((merged[1:] == merged[:-1]).sum())
                keep.append(shared * den >= num * (both - shared))
            mask = pa.array(keep, pa.bool_())
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(mask), batch.column(1).filter(mask)], names=["a", "b"])

    return run


def near_duplicates(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", num: int = NUM, den: int = DEN) -> DataFrame:
    """One row per document: id, ``n_shingles``, ``component_id``."""
    spark = docs.sparkSession
    scratch = Scratch(spark, "near_duplicates")
    rows = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).cast("binary").alias("t"))
    keyed = scratch.save(rows.mapInArrow(_keyed, "doc_id long, n long, k1 long, k2 long, " + ", ".join(f"{w} long" for w in _BITS)), "keyed")
    nodes = keyed.filter("n > 0 AND doc_id IS NOT NULL")
    classes = scratch.save(nodes.groupBy("k1", "k2").agg(F.min("doc_id").alias("cid"), F.first("n").alias("n"), *[F.first(w).alias(w) for w in _BITS]), "classes")
    member = scratch.save(nodes.select("doc_id", "k1", "k2").join(classes.select("k1", "k2", "cid"), ["k1", "k2"]).select("doc_id", "cid").distinct(), "member")

    def sketch(side: str) -> DataFrame:
        return classes.select(F.col("cid").alias(side), F.col("n").alias(f"n{side}"), *[F.col(w).alias(f"{w}{side}") for w in _BITS])

    live = rows.filter("t IS NOT NULL AND doc_id IS NOT NULL")
    frequent = live.mapInArrow(_frequent, "h long, n long").groupBy("h").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "h").limit(HOT_MOST)
    hot = np.sort(frequent.select("h").toPandas()["h"].to_numpy(np.int64).view(np.uint64))  # HOT_MOST numbers at most
    signed = live.mapInArrow(_signed(spark.sparkContext.broadcast(hot)), "sig long, id long").repartition("sig").sortWithinPartitions("sig", "id")
    # copies that reached several tasks are replaced by their class's id; few of them are sent along, many are joined
    copies = scratch.save(member.filter("doc_id <> cid"), "copies")
    small = F.broadcast if copies.count() <= BROADCAST_ROWS else (lambda df: df)
    stars = signed.mapInArrow(_stars, "sig long, id long, pivot long")
    for c in ("id", "pivot"):
        stars = stars.join(small(copies.select(F.col("doc_id").alias(c), F.col("cid").alias(f"{c}_class"))), c, "left").withColumn(c, F.coalesce(f"{c}_class", c)).drop(f"{c}_class")
    stars = scratch.save(stars.filter("id <> pivot").select("sig", "id", "pivot"), "stars")

    def possible(pairs: DataFrame) -> DataFrame:
        """Pairs of class ids that sizes and bitmaps allow, each once."""
        once = pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
        return once.join(sketch("a"), "a").join(sketch("b"), "b").filter(can_be_similar(num, den)).select("a", "b").distinct()

    def verified(pairs: DataFrame, name: str) -> DataFrame:
        needed = pairs.select(F.explode(F.array("a", "b")).alias("doc_id")).distinct()
        sets = scratch.save(live.join(needed, "doc_id", "left_semi").select("doc_id", "t").mapInArrow(_sets, "id long, elements binary").distinct(), f"{name}_sets")
        left, right = sets.select(F.col("id").alias("a"), F.col("elements").alias("x")), sets.select(F.col("id").alias("b"), F.col("elements").alias("y"))
        links = scratch.save(pairs.join(left, "a").join(right, "b").select("a", "b", "x", "y").mapInArrow(_verify(num, den), "a long, b long").distinct(), f"{name}_links")
        scratch.drop(f"{name}_sets")
        return links

    first = scratch.save(possible(stars.select(F.col("id").alias("a"), F.col("pivot").alias("b"))), "first")
    links = verified(first, "first")
    found = connected_components(links)

    # what is left: pairs of one bucket in different components
    joined = stars.select("sig", F.explode(F.array("id", "pivot")).alias("cid")).distinct()
    joined = joined.join(found.withColumnsRenamed({"node": "cid"}), "cid", "left").select("sig", "cid", F.coalesce("component", "cid").alias("g"))
    mixed = joined.groupBy("sig").agg(F.min("g").alias("lo"), F.max("g").alias("hi")).filter("lo <> hi").select("sig")
    open_ = scratch.save(joined.join(mixed, "sig", "left_semi"), "open")
    left = open_.withColumnsRenamed({"cid": "a", "g": "ga"}).join(sketch("a"), "a")
    right = open_.withColumnsRenamed({"cid": "b", "g": "gb"}).join(sketch("b"), "b")
    second = left.join(right, (left["sig"] == right["sig"]) & (F.col("a") < F.col("b")) & (F.col("ga") != F.col("gb")) & can_be_similar(num, den))
    second = second.select("a", "b").distinct().join(first, ["a", "b"], "left_anti")
    second = scratch.save(second, "second")
    if not second.isEmpty():
        links = links.union(verified(second, "second"))
        found = connected_components(links)

    whole = member.join(found.withColumnsRenamed({"node": "cid"}), "cid", "left").select("doc_id", F.coalesce("component", "cid").alias("component"))
    whole = connected_components(whole.select(F.col("doc_id").alias("a"), F.col("component").alias("b"))) if _repeated(member) else whole.select(F.col("doc_id").alias("node"), "component")
    scratch.drop("stars", "open")
    named = keyed.select("doc_id", F.col("n").alias("n_shingles")).join(whole.withColumnsRenamed({"node": "doc_id", "component": "component_id"}), "doc_id", "left")
    return named.select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"))


def _repeated(member: DataFrame) -> bool:
    """Whether an id has texts of several classes (rows of one id are one node)."""
    return not member.groupBy("doc_id").count().filter("count > 1").isEmpty()


def op3_near_duplicates(spark, sf_dir: str) -> DataFrame:
    """Contract of operator 3 over whole ``documents``."""
    return near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))


def keep_one(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", broadcast_rows: int = 500_000, **options) -> DataFrame:
    """The rows of ``docs`` with one document (the least id) of each group, rows that repeat an id once; columns unchanged."""
    scratch = Scratch(docs.sparkSession, "keep_one")
    found = near_duplicates(docs, doc_id=doc_id, text=text, **options)
    gone = scratch.save(found.filter("doc_id <> component_id").select(F.col("doc_id").alias(doc_id)).distinct(), "gone")
    few = gone.count() <= broadcast_rows
    kept = docs.join(F.broadcast(gone) if few else gone, doc_id, "left_anti")
    again = scratch.save(docs.filter(F.col(doc_id).isNotNull()).groupBy(doc_id).count().filter("count > 1").select(doc_id), "again")
    if again.isEmpty():
        return kept.select(docs.columns)
    once = kept.join(again, doc_id, "left_semi").dropDuplicates([doc_id])
    return kept.join(again, doc_id, "left_anti").select(docs.columns).unionByName(once.select(docs.columns))
