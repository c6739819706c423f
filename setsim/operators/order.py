"""Token order (rare first) and encoding of long sets into arrays of ranks.

Ranks are dense and global, yet no task sorts the vocabulary alone: it is range-partitioned by (frequency, token),
sorted within partitions, and each partition's ranks start at the number of tokens before it.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setsim.functions.bitmap import BitmapSpec, attach
from setsim.scratch import Scratch

#: A token of more sets than this is cut into blocks when postings are joined on it.
HOT_DF = 200_000
#: Rows of a part, and parts at most, in which long sets meet a vocabulary of more than so many tokens; a smaller one is sent out.
PART_ROWS, PARTS, SENT_TOKENS = 4_000_000, 4, 1_500_000
#: Codec of the tables of a collection: they are large, written once and kept.
CODEC = "zstd"


def build_vocab(long: DataFrame, scratch: Scratch) -> DataFrame:
    """``(tok, df, rank)`` in ascending order of (df, tok), ranks from 0."""
    counted = long.groupBy("tok").agg(F.count("*").alias("df"))
    sorted_ = counted.repartitionByRange("df", "tok").sortWithinPartitions("df", "tok")
    at = F.monotonically_increasing_id()
    placed = scratch.save(sorted_.select("tok", "df", F.shiftright(at, 33).cast("int").alias("part"), at.bitwiseAND(F.lit((1 << 33) - 1)).alias("i")), "vocab_parts", codec=CODEC)
    sizes = sorted((r["part"], r["count"]) for r in placed.groupBy("part").count().collect())  # one row per partition
    offsets, total = [], 0
    for part, n in sizes:
        offsets.append((part, total))
        total += n
    start = long.sparkSession.createDataFrame(offsets, "part int, start long")
    kind = "int" if total < 2**31 else "long"
    return placed.join(F.broadcast(start), "part").select("tok", "df", (F.col("start") + F.col("i")).cast(kind).alias("rank"))


def encode(long: DataFrame, vocab: DataFrame, scratch: Scratch, name: str) -> DataFrame:
    """The written ``(sid, n, toks)`` with ascending ranks of the table ``name``, which is deleted."""
    sent = vocab.count() <= SENT_TOKENS  # counted from the files' footers
    parts = 1 if sent else min(PARTS, 1 + long.count() // PART_ROWS)
    part = lambda df, k: df.filter(F.pmod(F.xxhash64("tok"), F.lit(parts)) == k) if parts > 1 else df
    ranks = vocab.select("tok", "rank")
    if sent:  # rows of a set stay together, so that what is shuffled are arrays of numbers
        ranks = F.broadcast(ranks)
    joined = [part(long, k).join(part(ranks, k), "tok").select("sid", "rank") for k in range(parts)]
    spent = [name]
    if parts > 1:  # each part is written before the next is shuffled
        spent = [f"{name}_ranked{k}" for k in range(parts)]
        joined = [scratch.save(df, made, codec=CODEC) for df, made in zip(joined, spent, strict=True)]
        scratch.drop(name)
    ranked = reduce(DataFrame.union, joined)
    toks = F.sort_array(F.collect_list("rank"))
    sets = scratch.save(ranked.groupBy("sid").agg(toks.alias("toks")).select("sid", F.size("toks").alias("n"), "toks"), f"{name}_sets", codec=CODEC)
    scratch.drop(*spent)
    return sets


@dataclass
class Collection:
    """An encoded collection: materialised sets, its vocabulary, and how many ranks occur in one set only.

    ``known`` keeps what was derived from them once: sketches (sets with bitmap words, written), statistics.
    """

    sets: DataFrame
    vocab: DataFrame
    singles: int = 0
    scratch: Scratch | None = field(default=None, repr=False)
    known: dict = field(default_factory=dict, repr=False)

    @property
    def spark(self):
        return self.sets.sparkSession

    def once(self, key: tuple, make):
        """What ``make()`` gives for a key, made at the first call."""
        if key not in self.known:
            self.known[key] = make()
        return self.known[key]

    def sketch(self, bitmap: BitmapSpec) -> DataFrame:
        """The sets with the bitmap's words, written once per variant, width and hash."""
        made = lambda: attach(self.sets, bitmap)
        name = f"sketch_{bitmap.variant}_{bitmap.b}_{bitmap.hash}"
        return self.once((name,), lambda: Scratch(self.spark, "sketch").save(made(), name, codec=CODEC) if self.scratch else made())

    def cell_sets(self, bitmap: BitmapSpec | None) -> DataFrame:
        """The sets for a join in cells, which writes them again: words that one row's tokens give are made on the way."""
        if bitmap is None:
            return self.sets
        return attach(self.sets, bitmap) if bitmap.variant != "probe" and bitmap.words <= 2 else self.sketch(bitmap)

    def hot(self, limit: int = HOT_DF) -> DataFrame | None:
        """``(rank, blocks)`` of tokens in more than ``limit`` sets; None without any. At most one per ``limit`` postings."""
        found = self.vocab.filter(F.col("df") > limit).select("rank", F.ceil(F.col("df") / limit).cast("int").alias("blocks"))
        return found if self.once(("hot", limit), lambda: not found.isEmpty()) else None


def prepare(long: DataFrame) -> Collection:
    """Vocabulary and encoding of one collection (what the measured joins exclude from their time)."""
    scratch = Scratch(long.sparkSession, "collection")
    long = scratch.save(long, "long", codec=CODEC)
    vocab = scratch.save(build_vocab(long, scratch), "vocab", codec=CODEC)
    scratch.drop("vocab_parts")
    sets = encode(long, vocab, scratch, "long")
    return Collection(sets, vocab, vocab.filter("df = 1").count(), scratch)


def prepare_pair(left: DataFrame, right: DataFrame) -> tuple[Collection, Collection]:
    """Two collections over the vocabulary of their union."""
    scratch = Scratch(left.sparkSession, "collections")
    left, right = (scratch.save(x, name, codec=CODEC) for x, name in ((left, "left"), (right, "right")))
    vocab = scratch.save(build_vocab(left.union(right), scratch), "vocab", codec=CODEC)
    scratch.drop("vocab_parts")
    singles = vocab.filter("df = 1").count()
    return tuple(Collection(encode(x, vocab, scratch, name), vocab, singles, scratch) for x, name in ((left, "left"), (right, "right")))
