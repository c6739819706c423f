"""Prefix joins of short sets in shards of tokens: sets go to the tokens of their prefixes once, pairs are made there.

Where sets are short and no token is frequent, neither postings nor cells are cheap: a token join shuffles every
candidate and reads both token arrays again, and cells compare all blocks with all others, which is quadratic in the
sets. Here a set is sent whole to the shards of its prefix tokens (rank modulo the number of shards; ranks are dense and
by frequency, so shards are alike), which grows with the sets. A shard is one row of a written table, its sets sorted by
size and id, and any join of the same or shorter prefixes reads it: the candidates are those of the token join, each
reported at its first common token, and they are filtered and verified in place.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType

from setsim.functions.bitmap import BitmapSpec
from setsim.functions.spec import SimSpec
from setsim.operators.cells import BLOCK_TOKENS, PAIR_SCHEMA, accepted, needed, ranges
from setsim.operators.order import CODEC, Collection
from setsim.scratch import Scratch

#: Sets of a shard about, sets that are dealt at once, and hits that are expanded at once.
SHARD_SETS, DEALT, HITS = 300_000, 200_000, 150_000
#: Tokens of a set and sets of a token at most, meetings at least, and tokens that cells hold as bits.
MOST_TOKENS, MOST_DF, LEAST_PAIRS, BITS = 64, 20_000, 100_000, 64
METHODS = ("prefix_length", "prefix_positional", "ell_prefix", "grouped_prefix")
SCHEMA = "shard int, sids binary, sizes binary, toks binary"


@dataclass(frozen=True)
class Rule:
    """What a shard does: prefix extension, filters, and whether groups of sets with equal size and prefix meet."""

    spec: SimSpec
    ell: int | None = None
    positional: bool = False
    grouped: bool = False
    bitmap: BitmapSpec | None = None
    limit: int | None = None

    def lengths(self) -> np.ndarray:
        """Prefix length per size."""
        return np.array([self.spec.prefix_len(n, self.ell or 1) if n else 0 for n in range(MOST_TOKENS + 1)], np.int64)


def rule_of(method: str, spec: SimSpec, *, ell: int = 1, bitmap: BitmapSpec | None = None, limit: int | None = None) -> Rule:
    """The rule of a join method."""
    return Rule(spec, ell if method == "ell_prefix" else None, method in ("prefix_positional", "grouped_prefix"), method == "grouped_prefix", bitmap, limit)


def sizes(collection: Collection) -> dict[int, int]:
    """Sets per size; nothing where some are too long."""

    def made() -> dict[int, int]:
        if (collection.sets.agg(F.max("n")).first()[0] or 0) > MOST_TOKENS:
            return {}
        return {r["n"]: r["c"] for r in collection.sets.groupBy("n").agg(F.count("*").alias("c")).collect()}

    return collection.once(("sizes",), made)


def sent(collection: Collection, lengths: np.ndarray) -> int:
    """Sets that all shards hold, at most."""
    return sum(c * int(lengths[n]) for n, c in sizes(collection).items())


def pays(collection: Collection, rule: Rule) -> bool:
    """Whether shards take the join: short sets, tokens of few sets, many meetings, and fewer bytes than cells send."""
    if not isinstance(collection.sets.schema["toks"].dataType.elementType, IntegerType):
        return False
    if rule.bitmap and (rule.bitmap.variant not in ("or", "xor") or rule.bitmap.hash != "mod" or rule.bitmap.words > 2):
        return False
    tokens = lambda: collection.vocab.agg(F.max("df"), F.sum(F.col("df") * (F.col("df") - 1) / 2), F.max("rank")).first()
    top, met, last = collection.once(("frequent",), tokens)
    if not met or top > MOST_DF or met < LEAST_PAIRS or last < BITS or not sizes(collection):
        return False
    lengths = rule.lengths()
    return sum(c * int(lengths[n]) * (12 + 4 * n) for n, c in sizes(collection).items()) <= cell_bytes(collection)


def cell_bytes(collection: Collection) -> int:
    """What the cells of a join would read, about: every block meets all others."""
    total, many = sum(n * c for n, c in sizes(collection).items()), sum(sizes(collection).values())
    blocks = -(-(total + 8 * many) // max(200_000, min(BLOCK_TOKENS, (total + 8 * many) // 6)))
    return (2 * total + 20 * many) * (blocks + 1)


def _deal(lengths: np.ndarray, parts: int, singles: int):
    """Sets by the shards of their prefix tokens, a row per shard and so many sets."""

    def dealt(batches: list[pa.RecordBatch]) -> pa.RecordBatch:
        table = pa.Table.from_batches(batches).combine_chunks()
        lists = table.column("toks").chunk(0)
        off = lists.offsets.to_numpy().astype(np.int64)
        flat, sid, n = lists.values.to_numpy(zero_copy_only=False), table.column("sid").to_numpy(), np.diff(off)
        k = lengths[n]
        tok = flat[ranges(off[:-1], k)]
        rows = np.repeat(np.arange(len(n)), k)[tok >= singles]
        key = np.unique((tok[tok >= singles] % parts).astype(np.int64) * len(n) + rows)
        shard, row = np.divmod(key, max(1, len(n)))
        found, first = np.unique(shard, return_index=True)
        ends = np.append(first, len(shard))
        held, width = flat[ranges(off[row], n[row])].astype(np.int32), np.concatenate([[0], np.cumsum(n[row])])
        cut = lambda values, at: pa.array([values[a:b].tobytes() for a, b in zip(at[:-1], at[1:], strict=True)], pa.binary())
        return pa.RecordBatch.from_arrays([pa.array(found.astype(np.int32)), cut(sid[row], ends), cut(n[row].astype(np.uint8), ends), cut(held, width[ends])], names=["shard", "sids", "sizes", "toks"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, many = [], 0
        for batch in batches:
            if batch.num_rows:
                held.append(batch)
                many += batch.num_rows
            if many >= DEALT:
                yield dealt(held)
                held, many = [], 0
        if held:
            yield dealt(held)

    return run


def _gather(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """One row per shard: its sets by size and id, ids as differences."""
    held: dict[int, list] = {}
    for batch in batches:
        for shard, *blobs in zip(*(batch.column(c).to_pylist() for c in ("shard", "sids", "sizes", "toks")), strict=True):
            held.setdefault(shard, []).append(blobs)
    for shard, blobs in held.items():
        sid, n, flat = (np.frombuffer(b"".join(x), kind) for x, kind in zip(zip(*blobs, strict=True), (np.int64, np.uint8, np.int32), strict=True))
        order = np.lexsort((sid, n))
        width = n.astype(np.int64)
        flat = flat[ranges((np.cumsum(width) - width)[order], width[order])]
        made = (np.diff(sid[order], prepend=0), n[order], flat)
        yield pa.RecordBatch.from_arrays([pa.array([shard], pa.int32()), *[pa.array([x.tobytes()], pa.binary()) for x in made]], names=["shard", "sids", "sizes", "toks"])


def table(collection: Collection, rule: Rule) -> tuple[int, DataFrame]:
    """The number of shards and their table: one that a join with prefixes as long has written, or a new one."""
    lengths, made = rule.lengths(), collection.known.setdefault(("shards",), [])
    many = sent(collection, lengths)
    for other, parts, shards in made:
        if all(other[n] >= lengths[n] for n in sizes(collection)) and sent(collection, other) <= 4 * many:
            return parts, shards
    parts = max(1, -(-many // SHARD_SETS))
    dealt = collection.sets.select("sid", "toks").mapInArrow(_deal(lengths, parts, collection.singles), SCHEMA)
    shards = dealt.repartitionById(parts, "shard").mapInArrow(_gather, SCHEMA)
    made.append((lengths, parts, Scratch(collection.spark, "shards").save(shards, "shards", codec=CODEC)))
    return made[-1][1:]


class Shard:
    """Sets sorted by size and id; ``tok[a]`` are their tokens at position a, where a set has none a number of its own."""

    def __init__(self, sids: bytes, sizes: bytes, toks: bytes):
        self.sid, self.n = np.cumsum(np.frombuffer(sids, np.int64)), np.frombuffer(sizes, np.uint8).astype(np.int64)
        many = len(self.n)
        self.tok = np.empty((int(self.n.max(initial=0)), many), np.int32)
        self.tok[:] = -1 - np.arange(many, dtype=np.int32)
        self.tok[ranges(np.zeros(many, np.int64), self.n), np.repeat(np.arange(many), self.n)] = np.frombuffer(toks, np.int32)

    def words(self, bitmap: BitmapSpec) -> np.ndarray:
        """The bitmap's words of every set, as ``bitmap.attach`` makes them."""
        out = np.zeros((bitmap.words, len(self.n)), np.uint64)
        for a, tok in enumerate(self.tok):
            place = tok % bitmap.b
            for k, word in enumerate(out):
                bit = np.where((a < self.n) & (place >> 6 == k), np.uint64(1) << (place & 63).astype(np.uint64), np.uint64(0))
                (np.bitwise_or if bitmap.variant == "or" else np.bitwise_xor)(word, bit, out=word)
        return out

    def meetings(self, rule: Rule, part: int, parts: int, singles: int, only: np.ndarray | None = None) -> Iterator[tuple[np.ndarray, ...]]:
        """``i, j, pos_i, pos_j`` of sets that meet at a prefix token of this shard, i after j in order, within the length filter."""
        k = rule.lengths()[self.n]
        tok = self.tok[: int(k.max(initial=0))]
        held = (np.arange(len(tok))[:, None] < k) & (tok >= singles) & (tok % parts == part)
        if only is not None:
            held &= only
        rows, pos = np.nonzero(held.T)
        if not len(rows):
            return
        at = tok[pos, rows] // parts
        order = np.argsort(at.astype(np.uint16) if at.max() < 65_536 else at, kind="stable")
        rows, pos, at = rows[order], pos[order], at[order]
        kinds, kind = np.unique(self.n, return_inverse=True)
        least = np.searchsorted(self.n, np.array([rule.spec.least_partner(int(x)) for x in kinds]))[kind]
        base = at.astype(np.int64) * len(self.n)
        start = np.searchsorted(base + rows, base + np.minimum(least, np.arange(len(self.n)))[rows])
        for p, q in expanded(start, np.arange(len(rows)) - start):
            yield rows[p], rows[q], pos[p], pos[q]

    def first(self, i: np.ndarray, j: np.ndarray, pos_i: np.ndarray, pos_j: np.ndarray) -> np.ndarray:
        """Whether no token before the one at which two sets meet is common."""
        out = np.ones(len(i), bool)
        some = np.flatnonzero((pos_i > 0) & (pos_j > 0))
        if len(some):
            i, j, pos = i[some], j[some], pos_i[some]
            other = [self.tok[b][j] for b in range(int(pos_j[some].max()))]
            early = np.zeros(len(some), bool)
            for a in range(int(pos.max())):
                own = self.tok[a][i]
                early |= _any(own, other) & (a < pos)
            out[some] = ~early
        return out

    def common(self, i: np.ndarray, j: np.ndarray, sides: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
        """Common tokens among the first so many of each side; the numbers of both sides are given per pair."""
        out = np.zeros(len(i), np.int64)
        most = np.maximum(*sides)
        low = 0
        for high in (2, 4, 6, 8, 12, 16, 32, MOST_TOKENS):
            some = np.flatnonzero((most > low) & (most <= high))
            low = high
            if not len(some):
                continue
            x, y, k, m = i[some], j[some], sides[0][some], sides[1][some]
            whole = (k == self.n[x]).all() and (m == self.n[y]).all()
            other = [self.tok[b][y] if whole else np.where(b < m, self.tok[b][y], -1 - y) for b in range(int(m.max()))]
            found = np.zeros(len(some), np.int16)
            for a in range(int(k.max())):
                met = _any(self.tok[a][x], other)
                found += met if whole else met & (a < k)
            out[some] = found
        return out

    def groups(self, rule: Rule) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Sets by equal size and prefix: the sets one group after the other, where each begins, and the group of each."""
        k = rule.lengths()[self.n]
        prefix = [np.where(a < k, self.tok[a], -1) for a in range(int(k.max(initial=0)))]
        mixed = self.n.astype(np.uint64)
        for p in prefix:  # equal groups become neighbours; a collision only cuts a group in two
            mixed = (mixed ^ p.astype(np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
            mixed ^= mixed >> np.uint64(29)
        order = np.argsort(mixed, kind="stable")
        differ = np.ones(len(order), bool)
        differ[1:] = self.n[order][1:] != self.n[order][:-1]
        for p in prefix:
            differ[1:] |= p[order][1:] != p[order][:-1]
        return order, np.flatnonzero(differ), np.cumsum(differ) - 1


def _any(own: np.ndarray, others: list[np.ndarray]) -> np.ndarray:
    out = own == others[0]
    for other in others[1:]:
        out |= own == other
    return out


def expanded(start: np.ndarray, many: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """``k`` and each of ``start[k] .. start[k] + many[k] - 1``, about ``HITS`` at once."""
    some = np.flatnonzero(many > 0)
    start, many = start[some], many[some]
    total = np.concatenate([[0], np.cumsum(many)])
    a = 0
    while a < len(some):
        b = max(a + 1, int(np.searchsorted(total, total[a] + HITS, "right")) - 1)
        yield np.repeat(some[a:b], many[a:b]), ranges(start[a:b], many[a:b])
        a = b


def pairs(shard: Shard, rule: Rule, part: int, parts: int, singles: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Candidate pairs, each once, after all filters."""
    if rule.grouped:
        yield from grouped(shard, rule, part, parts, singles)
        return
    keep_bits = _keep_bits(shard, rule)
    for i, j, pos_i, pos_j in shard.meetings(rule, part, parts, singles):
        keep = keep_bits(i, j)
        if keep is not None:
            i, j, pos_i, pos_j = i[keep], j[keep], pos_i[keep], pos_j[keep]
        keep = shard.first(i, j, pos_i, pos_j)
        i, j, pos_i, pos_j = i[keep], j[keep], pos_i[keep], pos_j[keep]
        n, m = shard.n[i], shard.n[j]
        if rule.positional:
            keep = np.minimum(n - pos_i, m - pos_j) >= needed(rule.spec, n, m)
            i, j = i[keep], j[keep]
        elif rule.ell:
            lengths = rule.lengths()
            keep = shard.common(i, j, (lengths[n], lengths[m])) >= np.minimum(rule.ell, needed(rule.spec, n, m))
            i, j = i[keep], j[keep]
        yield i, j


def grouped(shard: Shard, rule: Rule, part: int, parts: int, singles: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Groups of equal size and prefix meet and pass the positional filter as one set; their members follow."""
    members, begin, group = shard.groups(rule)
    many = np.diff(np.append(begin, len(members)))
    of = np.empty(len(members), np.int64)
    of[members] = group
    head = np.zeros(len(members), bool)
    head[members[begin]] = True
    keep_bits = _keep_bits(shard, rule)

    def kept(i: np.ndarray, j: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        i, j = np.maximum(i, j), np.minimum(i, j)
        keep = keep_bits(i, j)
        return (i, j) if keep is None else (i[keep], j[keep])

    for i, j, pos_i, pos_j in shard.meetings(rule, part, parts, singles, only=head):
        n, m = shard.n[i], shard.n[j]
        keep = np.minimum(n - pos_i, m - pos_j) >= needed(rule.spec, n, m)
        keep &= shard.first(i, j, pos_i, pos_j)
        g, h = of[i[keep]], of[j[keep]]
        for pair, at in expanded(np.zeros(len(g), np.int64), many[g] * many[h]):
            x, y = np.divmod(at, many[h[pair]])
            yield kept(members[begin[g[pair]] + x], members[begin[h[pair]] + y])
    # pairs within a group have the whole prefix in common: its first token reports them
    first = shard.tok[0][members] if len(shard.tok) else np.zeros(0, np.int32)
    lengths = rule.lengths()[shard.n[members]]
    here = (first >= singles) & (first % parts == part) & (lengths > 0)
    start = begin[group]
    for x, y in expanded(start, np.where(here, np.arange(len(members)) - start, 0)):
        yield kept(members[x], members[y])


def _keep_bits(shard: Shard, rule: Rule):
    """The bitmap filter of pairs of sets; None keeps all."""
    if rule.bitmap is None:
        return lambda i, j: None
    words = shard.words(rule.bitmap)

    def keep(i: np.ndarray, j: np.ndarray) -> np.ndarray:
        n, m = shard.n[i], shard.n[j]
        distance = sum(np.bitwise_count(w[i] ^ w[j]).astype(np.int64) for w in words)
        out = (n + m - distance) // 2 >= needed(rule.spec, n, m)
        return out if rule.limit is None else out | (np.maximum(n, m) > rule.limit)

    return keep


def shard_join(collection: Collection, rule: Rule) -> DataFrame:
    """Accepted pairs of a self-join with their overlaps."""
    parts, shards = table(collection, rule)
    singles = collection.singles

    def work(part: int, *blobs: bytes) -> Iterator[pa.RecordBatch]:
        shard = Shard(*blobs)
        for i, j in pairs(shard, rule, part, parts, singles):
            n, m = shard.n[i], shard.n[j]
            o = shard.common(i, j, (n, m))
            ok = accepted(rule, n, m, o)
            if ok.any():
                i, j, n, m, o = i[ok], j[ok], n[ok], m[ok], o[ok]
                yield pa.RecordBatch.from_arrays([pa.array(shard.sid[i]), pa.array(shard.sid[j]), *[pa.array(x.astype(np.int32)) for x in (n, m, o)]], names=["sid_r", "sid_s", "n_r", "n_s", "overlap"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                yield from work(*(batch.column(c)[k].as_py() for c in ("shard", "sids", "sizes", "toks")))

    return shards.mapInArrow(run, PAIR_SCHEMA)
