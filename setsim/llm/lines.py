"""Line deduplication as an exact set-similarity join, in DataFrame functions only.

A line is the set of its distinct lower-cased words (64-bit hashes). A line goes if an earlier line (by document id,
then line number) has a Jaccard similarity of ``num/den`` or more with it.

1. Words are ordered by rarity: occurrences over all texts, counted in ``CELLS`` hash cells, then by hash.
2. Lines of equal sets form one class, represented by its first line; copies of it go without any comparison.
3. Of every class the words of its prefix (size - least overlap + 1 rarest words) are posted, each with the class's
   number and document, a parity bitmap of 64 or 128 bits (its Hamming distance bounds the overlap), and one word for size,
   position and state.
   Classes that meet at a word pass length, positional and bitmap bounds inside the plan; survivors are verified on the
   full word sets.
4. At their rarest words all classes first meet only the earliest class posted there. A class that it makes redundant
   is settled: a group of m near copies costs m verifications. A frequent word is salted into groups of about
   ``STAR_ROWS`` classes, each with an earliest class of its own. Then all pairs meet whose later class is still open.

Defined results: lines without words (blank lines) always stay; null texts stay null; rows that repeat both id and
text are one document and get the same result; null ids come last; a document whose lines all go keeps an empty text
(``drop_emptied`` removes such rows).
"""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from setsim.llm.columns import free_name
from setsim.scratch import Scratch

#: ``BROADCAST_ROWS`` counts longs: at most 4 MB are sent to every executor.
NUM, DEN, CELLS, BROADCAST_ROWS, STAR_ROWS, ONE_WORD, PASSES = 4, 5, 1 << 16, 500_000, 100_000, 48, 2
_LAST = 2**63 - 1


def line_words(line: Column) -> Column:
    """Distinct words of a line as 64-bit hashes; blanks, tabs, carriage returns and form feeds separate words."""
    low = F.lower(line)
    odd = F.contains(line, F.lit("\t")) | F.contains(line, F.lit("\r")) | F.contains(line, F.lit("\x0b")) | F.contains(line, F.lit("\x0c"))
    words = F.when(odd, F.split(low, "[ \\t\\x0B\\f\\r]+")).otherwise(F.split(low, " "))  # one blank splits without a pattern
    # the empty word is taken out as a number: that copies no strings
    return F.array_remove(F.array_distinct(F.transform(words, lambda w: F.xxhash64(w))), F.xxhash64(F.lit("")))


def has_words(line: Column) -> Column:
    """Without a pattern: trimming stops at the first other character."""
    return F.ltrim(line, F.lit(" \t\x0b\x0c\r")) != ""


def _rarity(docs: DataFrame) -> Column:
    """Array literal: the rank of a hash cell's number of words over all texts, on a logarithmic scale up to 127, as the top byte of a long."""
    words = docs.select(F.explode(F.split(F.lower(F.replace("t", F.lit("\n"), F.lit(" "))), " ")).alias("w"))
    counted = words.groupBy(F.xxhash64("w").bitwiseAND(F.lit(CELLS - 1)).cast("int").alias("c")).count()
    cells = [0] * CELLS
    for c, n in counted.collect():  # at most CELLS rows
        cells[c] = min(127, round(4 * math.log2(n + 1)))
    return F.split(F.lit(",".join(str(n << 56) for n in cells)), ",").cast("array<bigint>")


def _needed(a: str, b: str, num: int, den: int) -> Column:
    return F.expr(f"(({a} + {b}) * {num} + {num + den - 1}) div {num + den}")


def _packed(n: str, p: str, more: Column | None = None) -> Column:
    """Size, position and a flag of a posting in one long."""
    packed = F.shiftleft(F.col(n), 32).bitwiseOR(F.shiftleft(F.col(p).cast("long"), 1))
    return packed if more is None else packed.bitwiseOR(more.cast("long"))


def _bounds(num: int, den: int) -> Column:
    """Length, position (0-based, at the shared word) and bitmap bounds on columns ``ma, wa, va`` and ``mb, wb, vb``."""
    na, nb = (F.shiftright(m, 32) for m in ("ma", "mb"))
    left_a, left_b = (n - F.shiftright(F.col(m).bitwiseAND(F.lit((1 << 32) - 1)), 1) for n, m in ((na, "ma"), (nb, "mb")))
    need = F.expr(f"((shiftright(`ma`, 32) + shiftright(`mb`, 32)) * {num} + {num + den - 1}) div {num + den}")
    length = F.least(na, nb) * den >= F.greatest(na, nb) * num
    apart = lambda *words: sum((F.bit_count(F.col(f"{w}a").bitwiseXOR(F.col(f"{w}b"))) for w in words), F.lit(0))
    folded = F.bit_count(F.col("wa").bitwiseXOR(F.col("va")).bitwiseXOR(F.col("wb")).bitwiseXOR(F.col("vb")))
    distance = F.when(F.least(na, nb) > ONE_WORD, apart("w", "v")).otherwise(folded)
    return length & (F.least(left_a, left_b) >= need) & (na + nb - distance >= 2 * need)


def _classes(docs: DataFrame, num: int, den: int) -> DataFrame:
    """Lines of equal word sets as one row: size, bitmap, rarest words (the prefix) and the first line's place."""
    cells = _rarity(docs)
    # lambdas are interpreted: one hash a word, no cast of the index, and no null that would have longs sorted as objects
    placed = lambda w: cells[w.bitwiseAND(F.lit(CELLS - 1))].bitwiseOR(F.shiftrightunsigned(w, 8))
    lines = docs.filter("t IS NOT NULL").select("d", "h", F.posexplode(F.split("t", "\n")).alias("ln", "line")).filter(has_words(F.col("line")))
    words = lines.select("d", "h", "ln", F.sort_array(F.transform(line_words(F.col("line")), placed)).alias("order"))
    bit = lambda w: F.call_function("shiftleft", F.lit(1).cast("long"), w.bitwiseAND(F.lit(63)).cast("int"))
    parity = lambda words: F.aggregate(words, F.lit(0).cast("long"), lambda acc, w: acc.bitwiseXOR(bit(w)))
    n = F.size("order").cast("long")
    # lines of more words spread their parities over two words; both of them folded are what a shorter line has in one
    upper = F.when(n > ONE_WORD, parity(F.filter("order", lambda w: w.bitwiseAND(F.lit(64)) > 0))).otherwise(F.lit(0).cast("long"))
    prefix = F.transform(F.slice("order", 1, (n - F.expr(f"(CAST(size(`order`) AS BIGINT) * {num} + {den - 1}) div {den}") + 1).cast("int")), lambda w: F.shiftrightunsigned(w, 24))
    keyed = words.select("d", "h", "ln", n.alias("n"), F.xxhash64("order").alias("k1"), F.xxhash64("order", F.lit(1)).alias("k2"), parity(F.col("order")).alias("w"), upper.alias("v"), prefix.alias("prefix"))
    first = F.min(F.struct("d", "ln", "h", "w", "v", "prefix"))
    classes = keyed.groupBy("k1", "k2", "n").agg(first.alias("f")).select(F.monotonically_increasing_id().alias("cid"), "n", "f.d", "f.ln", "f.h", "f.w", "f.v", "f.prefix")
    return classes.withColumn("w", F.col("w").bitwiseXOR(F.col("v")))


def redundant_lines(docs: DataFrame, scratch: Scratch, *, num: int = NUM, den: int = DEN) -> DataFrame:
    """From ``(d, h, t)``: the kept lines with words, as ``(d, h, ln)``; every other line with words is redundant."""
    classes = scratch.save(_classes(docs, num, den), "classes")
    repeated = not docs.groupBy("d", "h").count().filter("count > 1").isEmpty()  # else a class's words are read once

    def small(df: DataFrame) -> DataFrame:
        """For tables of one long a row."""
        return F.broadcast(df) if df.count() <= BROADCAST_ROWS else df

    def verified(pairs: DataFrame, name: str) -> DataFrame:
        """Later classes ``cid`` of the pairs that are similar."""
        needed = scratch.save(pairs.select(F.explode(F.array("a", "b")).alias("cid")).distinct(), f"{name}_needed")
        place = scratch.save(classes.select("cid", "d", "ln", "h").join(small(needed), "cid"), f"{name}_place")
        own = place.groupBy("d", "h").agg(F.collect_list(F.struct("ln", "cid")).alias("at"))
        few = 4 * place.count() <= BROADCAST_ROWS  # d, h, ln, cid
        texts = docs.join(F.broadcast(own) if few else own, ["d", "h"]).select("d", "h", F.split("t", "\n").alias("ls"), "at").select("d", "h", "ls", F.explode("at").alias("x"))
        sets = texts.select("x.cid", line_words(F.element_at("ls", F.col("x.ln") + 1)).alias("words"), F.struct("d", "x.ln", "h", "x.cid").alias("o"))
        sets = scratch.save(sets.dropDuplicates(["cid"]) if repeated else sets, f"{name}_sets")
        both = pairs.join(sets.select(F.col("cid").alias("a"), F.col("words").alias("x"), F.col("o").alias("oa")), "a").join(sets.select(F.col("cid").alias("b"), F.col("words").alias("y"), F.col("o").alias("ob")), "b")
        shared = F.size(F.array_intersect("x", "y"))
        similar = both.filter(shared * (num + den) >= (F.size("x") + F.size("y")) * num)
        later = scratch.save(similar.select(F.greatest("oa", "ob")["cid"].alias("cid")).distinct(), f"{name}_later")
        scratch.drop(*(f"{name}_{x}" for x in ("needed", "place", "sets")))
        return later

    def pairs_of(df: DataFrame) -> DataFrame:
        return df.select(F.least("ca", "cb").alias("a"), F.greatest("ca", "cb").alias("b")).distinct()

    # first every class meets only the earliest class at its rarest words (the shorter of its two prefixes)
    short = (F.col("n") - _needed("n", "n", num, den) + 1).cast("int")
    rarest = classes.select(F.col("cid").alias("ca"), "d", "n", F.col("w").alias("wa"), F.col("v").alias("va"), F.posexplode(F.slice("prefix", 1, short)).alias("p", "word"))
    groups = F.pow(F.lit(2.0), F.shiftright("word", 32) / 4) / STAR_ROWS  # by the frequency of the word's cell
    salt = F.when(groups > 1, F.pmod(F.xxhash64("ca"), F.ceil(groups))).otherwise(F.lit(0).cast("long"))
    rarest = rarest.select("ca", "d", "wa", "va", "word", _packed("n", "p").alias("ma"), salt.alias("salt"))
    earliest = F.first(F.struct("ca", "ma", "wa", "va")).over(Window.partitionBy("word", "salt").orderBy("d", "ca"))
    star = rarest.withColumn("f", earliest).filter("ca <> f.ca").select("ca", "ma", "wa", "va", *[F.col(f"f.{x}a").alias(f"{x}b") for x in "cmwv"])
    met = scratch.save(pairs_of(star.filter(_bounds(num, den))), "first")
    gone = verified(met, "first")

    # then all pairs whose later class is still open; the smaller class of a pair needs the shorter prefix only
    flagged = classes.join(small(gone.withColumn("gone", F.lit(True))), "cid", "left").withColumn("open", F.col("gone").isNull())

    def posted(side: str, prefix: Column, turn: int) -> DataFrame:
        postings = flagged.select("cid", "d", "n", "w", "v", "open", F.posexplode(prefix).alias("p", "word")).filter(F.pmod("word", F.lit(PASSES)) == turn)
        return postings.select(*[F.col(c).alias(f"{x}{side}") for c, x in (("cid", "c"), ("d", "d"), ("w", "w"), ("v", "v"), ("word", "word"))], _packed("n", "p", F.col("open")).alias(f"m{side}"))

    na, nb = F.shiftright("ma", 32), F.shiftright("mb", 32)
    sizes = (nb < na) | ((nb == na) & (F.col("cb") < F.col("ca")))
    open_a, open_b = (F.col(m).bitwiseAND(F.lit(1)) == 1 for m in ("ma", "mb"))
    later_open = F.when(F.col("da") > F.col("db"), open_a).when(F.col("da") < F.col("db"), open_b).otherwise(open_a | open_b)
    near = []
    for k in range(PASSES):  # one part of the words after the other: postings of one part only are on disk at a time
        larger, smaller = posted("a", F.col("prefix"), k), posted("b", F.slice("prefix", 1, short), k)
        near.append(scratch.save(pairs_of(larger.join(smaller, (F.col("worda") == F.col("wordb")) & sizes & later_open & _bounds(num, den))), f"near{k}"))
    rest = scratch.save(reduce(DataFrame.union, near).distinct().join(met, ["a", "b"], "left_anti"), "rest")
    gone = scratch.save(gone.union(verified(rest, "rest")).distinct(), "gone")
    return classes.join(small(gone), "cid", "left_anti").select("d", "h", "ln")


def dedup_lines(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", num: int = NUM, den: int = DEN, drop_emptied: bool = False, counts: bool = False) -> DataFrame:
    """All rows and columns of ``docs`` with redundant lines taken out of ``text`` (and their number, with ``counts``)."""
    d, h, k, left = (free_name(docs, x) for x in ("__d", "__h", "__kept", "__stays"))
    key = {d: F.coalesce(F.col(doc_id).cast("long"), F.lit(_LAST)), h: F.xxhash64(F.col(text))}
    slim = docs.select(key[d].alias("d"), key[h].alias("h"), F.col(text).alias("t"))
    scratch, work = Scratch(docs.sparkSession, "lines_kept"), Scratch(docs.sparkSession, "lines")
    kept = scratch.save(redundant_lines(slim, work, num=num, den=den).groupBy("d", "h").agg(F.array_sort(F.collect_list("ln")).alias(k)).withColumnsRenamed({"d": d, "h": h}), "kept")
    work.drop()
    keyed = docs.withColumns(key)
    joined = keyed.join(kept, [d, h], "left")
    lines = F.split(F.col(text), "\n")
    stays = F.filter(F.transform(lines, lambda x, i: F.when(F.array_contains(F.coalesce(F.col(k), F.array().cast("array<int>")), i) | ~has_words(x), x)), lambda x: x.isNotNull())
    joined = joined.withColumn(left, stays)
    columns = [F.col(f"`{c}`") if c != text else F.when(F.col(text).isNotNull(), F.array_join(left, "\n")).alias(text) for c in docs.columns]
    if drop_emptied:
        joined = joined.filter(F.col(text).isNull() | (F.size(left) > 0) | (F.size(lines) == 0))
    if counts:
        columns += [F.coalesce(F.size(lines), F.lit(0)).cast("long").alias("n_lines"), F.coalesce(F.size(lines) - F.size(left), F.lit(0)).cast("long").alias("n_removed")]
    return joined.select(columns)


def op9_line_dedup(spark, sf_dir: str) -> DataFrame:
    """Operator 9 over whole ``documents``: texts without redundant lines, with counts."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return dedup_lines(docs, counts=True).select("doc_id", "n_lines", "n_removed", "text")
