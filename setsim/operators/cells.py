"""Prefix joins of long or frequent-token sets in cells: pairs are made, filtered and verified in one task and never stored.

A token join writes every candidate, and its verification both token arrays per candidate. Where candidates are many
more than tokens that is what fills the disks. Here sets are cut into blocks by size range and hash; a cell is a pair
of blocks whose sizes admit similar sets, and holds the tokens of both (as differences, two bytes each for most). Its
task joins the prefixes of the two blocks token by token, so the candidates are those of the token join: the sets of a
block are sorted by size and id, hence a set's admissible partners are one range of every posting list. Only accepted
pairs, or counts per size, leave a cell. The blocks are written once and a cell's task reads its two, so the disk holds
every set once; with more cells than ``READ_CELLS`` a set is sent once per cell instead.
"""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setsim.functions.bitmap import BitmapSpec
from setsim.functions.spec import SimSpec
from setsim.operators.block import MOST_SETS, needed_matrix
from setsim.operators.candidates import prefix_postings
from setsim.scratch import Scratch

#: Tokens of a block at most (a larger set is a block of its own), hits that are expanded at once, and slots for uniqueness.
BLOCK_TOKENS, HITS, SLOTS, GUARD = 12_000_000, 2_000_000, 8_000_000, 512
#: Rows of both sides of a tile of all pairs, pairs of a tile from which a wider guard is asked, its bits at most, and rows that get it at once.
TILE, FEW, WIDEST, SEGMENT = (64, 4096), 64, 16_384, 512
#: Cells at most that read their blocks from files: each is two scans of the plan.
READ_CELLS = 300
PAIR_SCHEMA = "sid_r long, sid_s long, n_r int, n_s int, overlap int"
COUNT_SCHEMA = "n int, candidates long, kept long, similar long"


@dataclass(frozen=True)
class Rule:
    """What a cell does: prefix extension, filters, and whether it emits accepted pairs or counts."""

    spec: SimSpec
    ell: int | None = None
    positional: bool = False
    words: tuple[str, ...] = ()
    limit: int | None = None
    counts: bool = False
    verify: bool = True
    all_pairs: bool = False


def needed(spec: SimSpec, n: np.ndarray, m: np.ndarray) -> np.ndarray:
    """Least overlap per pair of sizes, exact."""
    n, m = n.astype(np.int64), m.astype(np.int64)
    p, q = spec.num, spec.den
    if spec.measure == "overlap":
        return np.full(len(n), p, np.int64)
    if spec.measure == "jaccard":
        return -(-p * (n + m) // (p + q))
    if spec.measure == "dice":
        return -(-p * (n + m) // (2 * q))
    sizes, at = np.unique(np.stack([n, m], 1), axis=0, return_inverse=True)
    each = np.array([needed_matrix(spec, sizes[k : k + 1, 0], sizes[k : k + 1, 1])[0, 0] for k in range(len(sizes))], np.int64)
    return each[at.ravel()]


class Block:
    """Sets sorted by size and id, their tokens flat; ``skip`` tokens that occur in no other set are left out in front."""

    def __init__(self, table: pa.Table, words: tuple[str, ...]):
        n, sid = table.column("n").to_numpy(), table.column("sid").to_numpy()
        order = np.lexsort((sid, n))
        self.n, self.sid = n[order].astype(np.int64), sid[order]
        lo, hi = (_flat(table.column(c)) for c in ("lo", "hi"))
        starts = np.concatenate([[0], np.cumsum(lo[0])])
        sizes = lo[0][order]
        self.off = np.concatenate([[0], np.cumsum(sizes)])
        self.tok = np.empty(self.off[-1], np.uint32)
        for a in range(0, len(order), SEGMENT):  # by few rows, as a block is large
            rows, b = order[a : a + SEGMENT], min(len(order), a + SEGMENT)
            at = ranges(starts[rows], sizes[a:b])
            total = np.cumsum(lo[1][at].astype(np.int64) | (hi[1][at].astype(np.int64) << 16))
            base = np.concatenate([[0], total])[self.off[a:b] - self.off[a]]
            self.tok[self.off[a] : self.off[b]] = total - np.repeat(base, sizes[a:b])
        self.skip = self.n - sizes
        self.words = np.stack([table.column(w).to_numpy() for w in words], 1).view(np.uint64)[order] if words else None
        self.known: dict[int, tuple[np.ndarray, np.ndarray]] = {}

    def __len__(self) -> int:
        return len(self.n)

    def prefixes(self, rule: Rule) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Row, position and token of every prefix token that another set may hold."""
        kinds, at = np.unique(self.n, return_inverse=True)
        k = np.array([rule.spec.prefix_len(int(x), rule.ell or 1) for x in kinds], np.int64)[at] if len(kinds) else self.n
        k = np.maximum(0, k - self.skip)
        flat = ranges(self.off[:-1], k)
        rows = np.repeat(np.arange(len(self)), k)
        return rows, flat - self.off[rows] + self.skip[rows], self.tok[flat].astype(np.int64)

    def bits(self, rule: Rule) -> tuple[np.ndarray, np.ndarray]:
        """Prefixes and whole sets as one word each, for tokens below 64."""
        out = []
        for rows, tok in (self.prefixes(rule)[::2], (np.repeat(np.arange(len(self)), np.diff(self.off)), self.tok)):
            word = np.zeros(len(self), np.uint64)
            np.bitwise_or.at(word, rows, np.uint64(1) << tok.astype(np.uint64))
            out.append(word)
        return tuple(out)

    def parity(self, bits: int = GUARD, first: int = 0, last: int | None = None) -> np.ndarray:
        """Words of so many bits of a run of rows: the parity of a set's tokens per slot."""
        last = len(self) if last is None else last
        out = np.empty((last - first, bits // 64), np.uint64)
        step = max(1, (4096 * GUARD) // bits)
        for a in range(first, last, step):
            b = min(last, a + step)
            rows = np.repeat(np.arange(b - a), np.diff(self.off[a : b + 1]))
            load = np.bincount(rows * bits + self.tok[self.off[a] : self.off[b]] % bits, minlength=(b - a) * bits)
            out[a - first : b - first] = np.packbits((load & 1).astype(np.uint8).reshape(b - a, bits), axis=1).view(np.uint64)
        return out

    def columns(self, bits: int, first: int, last: int) -> np.ndarray:
        """The words of a run of rows, word by word: of a guard of so many bits, or the bitmap's (0); made where they are asked for."""
        if bits not in self.known:
            known = np.ascontiguousarray(self.words.T) if not bits else np.empty((bits // 64, len(self)), np.uint64)
            self.known[bits] = known, np.full(-(-len(self) // SEGMENT), not bits)
        known, done = self.known[bits]
        for k in range(first // SEGMENT, -(-last // SEGMENT)):
            if not done[k]:
                a, b = k * SEGMENT, min(len(self), (k + 1) * SEGMENT)
                known[:, a:b], done[k] = self.parity(bits, a, b).T, True
        return known[:, first:last]


def ranges(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """``starts[k] .. starts[k] + sizes[k] - 1`` of all k, one after the other."""
    total = int(sizes.sum())
    return np.arange(total) + np.repeat(starts - (np.cumsum(sizes) - sizes), sizes)


def _flat(column: pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """Numbers per row and all numbers of a column of 16-bit numbers as binary."""
    sizes, data = [], []
    for c in column.chunks:
        off = np.frombuffer(c.buffers()[1], np.int32)[c.offset : c.offset + len(c) + 1] if len(c) else np.zeros(1, np.int32)
        sizes.append(np.diff(off) // 2)
        data.append(np.frombuffer(c.buffers()[2], np.uint8)[off[0] : off[-1]].view(np.uint16) if off[-1] > off[0] else np.zeros(0, np.uint16))
    return np.concatenate(sizes).astype(np.int64), np.concatenate(data)


def overlap_of(x: Block, y: Block, i: np.ndarray, j: np.ndarray, mark: np.ndarray) -> np.ndarray:
    """Exact overlaps of pairs of rows, i ascending."""
    out = np.zeros(len(i), np.int64)
    bounds = np.concatenate([[0], np.flatnonzero(np.diff(i)) + 1, [len(i)]]) if len(i) else np.zeros(1, int)
    sizes = np.diff(y.off)
    for a, b in zip(bounds[:-1], bounds[1:], strict=True):
        own = x.tok[x.off[i[a]] : x.off[i[a] + 1]]
        mark[own] = 1
        few = max(1, min(4096, HITS // max(1, len(own))))  # the other sets are no larger
        for c in range(a, b, few):
            js = j[c : min(b, c + few)]
            found = np.concatenate([[0], np.cumsum(mark[y.tok[ranges(y.off[js], sizes[js])]], dtype=np.int64)])
            ends = np.cumsum(sizes[js])
            out[c : c + len(js)] = found[ends] - found[ends - sizes[js]]
        mark[own] = 0
    return out


def candidates_of(x: Block, y: Block, rule: Rule) -> Iterator[tuple[np.ndarray, ...]]:
    """Unique candidates ``i, j, pos_i, pos_j, overlap`` with y's set the smaller one (ties by id), i ascending, in parts.

    Positions and overlaps are None where they are not known.
    """
    spec, width = rule.spec, len(y)
    kinds, at = np.unique(x.n, return_inverse=True)
    least = np.searchsorted(y.n, np.array([spec.least_partner(int(k)) for k in kinds]))[at]
    # rows of y before (n, sid) of x
    first, last = np.searchsorted(y.n, x.n), np.searchsorted(y.n, x.n, "right")
    merged = np.concatenate([y.sid, x.sid])
    ids = np.unique(merged, return_inverse=True)[1]
    y_key, x_key = y.n * (len(merged) + 1) + ids[:width], x.n * (len(merged) + 1) + ids[width:]
    until = np.clip(np.searchsorted(y_key, x_key), first, last)
    if rule.all_pairs and rule.words and rule.verify and not rule.counts and rule.limit is None:
        yield from tiled(x, y, rule, least, until)
        return
    if rule.all_pairs:
        per = np.maximum(0, until - least)
        for a, b in chunks(per, len(x)):
            i = np.repeat(np.arange(a, b), per[a:b])
            yield i, ranges(least[a:b], per[a:b]), None, None, None
        return
    if max(x.tok.max(initial=0), y.tok.max(initial=0)) < 64:
        yield from dense(x, y, rule, least, until)
        return
    rows, pos, tok = x.prefixes(rule)
    y_rows, y_pos, y_tok = y.prefixes(rule)
    order = np.argsort(y_tok * width + y_rows)
    y_rows, y_pos, key = y_rows[order], y_pos[order], (y_tok * width + y_rows)[order]
    start = np.searchsorted(key, tok * width + least[rows])
    met = np.maximum(0, np.searchsorted(key, tok * width + until[rows]) - start)
    some = met > 0
    rows, pos, start, met = rows[some], pos[some], start[some], met[some]
    per = np.bincount(rows, met, len(x)).astype(np.int64)
    ends = np.searchsorted(rows, np.arange(len(x) + 1))
    most = max(1, SLOTS // max(1, width))
    seen = np.zeros(min(len(x), most) * width, np.int32) if most > 64 else None
    for a, b in chunks(per, most if most > 64 else len(x)):
        s = slice(ends[a], ends[b])
        if s.start == s.stop:
            continue
        which = np.repeat(np.arange(s.start, s.stop), met[s])
        at = ranges(start[s], met[s])
        j = y_rows[at]
        slot = (rows[which] - a) * width + j
        if seen is None:  # wide blocks of short sets
            once, place = np.unique(slot, return_index=True, return_inverse=True)[1:]
            times = np.bincount(place)
        else:
            number = np.arange(len(slot), dtype=np.int32)
            seen[slot[::-1]] = number[::-1]  # of several numbers for a slot the last written stays: the first meeting
            place = seen[slot]
            once = np.flatnonzero(place == number)
            times = np.bincount(place, minlength=len(slot))[once] if rule.ell else None
        if rule.ell:
            once = once[times >= np.minimum(rule.ell, needed(spec, x.n[rows[which[once]]], y.n[j[once]]))]
        yield rows[which[once]], j[once], pos[which[once]], y_pos[at[once]], None


def dense(x: Block, y: Block, rule: Rule, least: np.ndarray, until: np.ndarray) -> Iterator[tuple[np.ndarray, ...]]:
    """The same candidates where at most 64 tokens exist: prefixes and sets are words of bits, and all pairs of a tile meet at once.

    Where accepted pairs are asked for, the exact overlap of the bits is compared here as well.
    """
    (px, fx), (py, fy) = (b.bits(rule) for b in (x, y))
    top = int(max(x.n.max(initial=0), y.n.max(initial=0)))
    side = np.arange(1, top + 1)
    need = np.clip(needed_matrix(rule.spec, side, side), 0, 255).astype(np.uint8)
    exact = rule.verify and not rule.counts
    for a in range(0, len(x), 64):
        b = min(len(x), a + 64)
        low, high = int(least[a:b].min()), int(until[a:b].max())
        inner = int(least[a:b].max()), int(until[a:b].min())
        for c in range(low, high, 4096):
            d = min(high, c + 4096)
            meet = px[a:b, None] & py[None, c:d]
            wanted = need[x.n[a:b] - 1][:, y.n[c:d] - 1] if exact or rule.ell else None
            keep = np.bitwise_count(meet) >= np.minimum(np.uint8(min(rule.ell, 255)), wanted) if rule.ell else meet != 0
            if c < inner[0] or d > inner[1]:
                at = np.arange(c, d)
                keep &= (at >= least[a:b, None]) & (at < until[a:b, None])
            if exact:
                keep &= np.bitwise_count(fx[a:b, None] & fy[None, c:d]) >= wanted
            i, j = np.divmod(np.flatnonzero(keep), d - c)
            i, j = i + a, j + c
            if not len(i):
                continue
            pos_i = pos_j = None
            if rule.positional:  # of the first common prefix token: the set's tokens below it
                common = px[i] & py[j]
                below = (common & (~common + np.uint64(1))) - np.uint64(1)
                pos_i, pos_j = np.bitwise_count(fx[i] & below).astype(np.int64) + x.skip[i], np.bitwise_count(fy[j] & below).astype(np.int64) + y.skip[j]
            yield i, j, pos_i, pos_j, np.bitwise_count(fx[i] & fy[j]).astype(np.int64) if exact else None


def tiled(x: Block, y: Block, rule: Rule, least: np.ndarray, until: np.ndarray) -> Iterator[tuple[np.ndarray, ...]]:
    """All pairs whose bitmaps may be near enough: every pair of a tile is compared at once, without an index per pair.

    A tile's rows take the largest distance that any of its partners admits, so the exact test is left to the caller. Where
    many pairs pass, as bitmaps are full, parities of more bits (to fit the sizes) drop pairs that verification would drop.
    """
    held: list[tuple[np.ndarray, np.ndarray]] = []
    room = (np.empty(TILE[0] * TILE[1], np.uint64), np.empty(TILE[0] * TILE[1], np.uint8))
    for a in range(0, len(x), TILE[0]):
        b = min(len(x), a + TILE[0])
        n, own = np.unique(x.n[a:b], return_inverse=True)
        inner = int(least[a:b].max()), int(until[a:b].min())
        for c in range(int(least[a:b].min()), int(until[a:b].max()), TILE[1]):
            d = min(int(until[a:b].max()), c + TILE[1])
            m = np.unique(y.n[c:d])
            most = (n[:, None] + m[None, :] - 2 * needed_matrix(rule.spec, n, m)).max(1).clip(0)[own]
            keep = _near(x.columns(0, a, b), y.columns(0, c, d), most[:, None], room)
            if c < inner[0] or d > inner[1]:
                at = np.arange(c, d)
                keep &= (at >= least[a:b, None]) & (at < until[a:b, None])
            many = np.count_nonzero(keep)
            bits = _guard_bits(int(most.max()), int(x.n[b - 1] + y.n[(c + d) // 2])) if many > FEW else 0
            if bits and 4 * many > keep.size:
                skipped = most[:, None] - x.skip[a:b, None] - y.skip[None, c:d]
                keep &= _near(x.columns(bits, a, b), y.columns(bits, c, d), skipped, room)
                bits = 0
            i, j = np.divmod(np.flatnonzero(keep), d - c)
            if bits:
                u, v = x.columns(bits, a, b), y.columns(bits, c, d)
                distance = np.zeros(len(i), np.int64)
                for k in range(len(u)):
                    distance += np.bitwise_count(u[k][i] ^ v[k][j])
                near = distance <= most[i] - x.skip[a:b][i] - y.skip[c:d][j]
                i, j = i[near], j[near]
            if len(i):
                held.append((i + a, j + c))
            if sum(len(i) for i, _ in held) >= HITS // 8:
                yield _merged(held)
                held = []
    if held:
        yield _merged(held)


def _near(u: np.ndarray, v: np.ndarray, most: np.ndarray, room: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    """Whether words of rows and rows differ in so many bits at most."""
    shape = u.shape[1], v.shape[1]
    word, bits = (r[: shape[0] * shape[1]].reshape(shape) for r in room)
    total = np.zeros(shape, np.uint8 if 64 * len(u) < 256 else np.uint16)
    for k in range(len(u)):
        np.bitwise_xor(u[k][:, None], v[k][None, :], out=word)
        np.bitwise_count(word, out=bits)
        np.add(total, bits, out=total)
    if most.shape[1] == 1:  # a limit per row, in the type of the sums
        return total <= np.minimum(most, np.iinfo(total.dtype).max).astype(total.dtype)
    return total <= most


def _guard_bits(most: int, size: int) -> int:
    """Bits at which the parities of sets of so many tokens together, hardly any in common, differ clearly more; 0 for none."""
    bits = GUARD
    while bits <= WIDEST:
        if most <= 0.6 * bits / 2 * -np.expm1(-1.6 * size / bits):
            return bits
        bits *= 2
    return 0


def _merged(held: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, ...]:
    i, j = (np.concatenate(x) for x in zip(*held, strict=True))
    order = np.argsort(i, kind="stable")
    return i[order], j[order], None, None, None


def chunks(per: np.ndarray, most_rows: int) -> Iterator[tuple[int, int]]:
    """Runs of rows with about ``HITS`` hits and at most so many rows (one row at least)."""
    total = np.concatenate([[0], np.cumsum(per)])
    a = 0
    while a < len(per):
        b = int(np.searchsorted(total, total[a] + HITS, "right")) - 1
        b = min(max(b, a + 1), a + most_rows, len(per))
        yield a, b
        a = b


def accepted(rule: Rule, n: np.ndarray, m: np.ndarray, o: np.ndarray) -> np.ndarray:
    return (o > 0) & (o >= needed(rule.spec, n, m))


def work(x: Block, y: Block, rule: Rule, mark: np.ndarray, guards: tuple | None) -> Iterator[pa.RecordBatch]:
    tally: dict[int, np.ndarray] = {}
    for i, j, pos_i, pos_j, o in candidates_of(x, y, rule):
        n, m = x.n[i], y.n[j]
        need = needed(rule.spec, n, m)
        if rule.positional and pos_i is not None:
            keep = np.minimum(n - pos_i, m - pos_j) >= need
            i, j, n, m, need, o = i[keep], j[keep], n[keep], m[keep], need[keep], o if o is None else o[keep]
        tried = np.bincount(n, minlength=1) if rule.counts else None
        if rule.words:
            keep = (n + m - _distance(x.words, y.words, i, j)) // 2 >= need
            if rule.limit is not None:
                keep |= np.maximum(n, m) > rule.limit
            i, j, n, m, need, o = i[keep], j[keep], n[keep], m[keep], need[keep], o if o is None else o[keep]
        kept = np.bincount(n, minlength=1) if rule.counts else None
        if rule.verify and o is None:
            if guards and len(i):
                keep = (n + m - _distance(*guards, i, j) - (x.skip[i] + y.skip[j])) // 2 >= need
                i, j, n, m = i[keep], j[keep], n[keep], m[keep]
            o = overlap_of(x, y, i, j, mark)
            ok = accepted(rule, n, m, o)
            i, j, n, m, o = i[ok], j[ok], n[ok], m[ok], o[ok]
        if rule.counts:
            for k, sums in enumerate((tried, kept, np.bincount(n, minlength=1))):
                for size in np.flatnonzero(sums):
                    tally.setdefault(int(size), np.zeros(3, np.int64))[k] += sums[size]
        elif len(i):
            yield pa.RecordBatch.from_arrays([pa.array(x.sid[i]), pa.array(y.sid[j]), pa.array(n.astype(np.int32)), pa.array(m.astype(np.int32)), pa.array(o.astype(np.int32))], names=["sid_r", "sid_s", "n_r", "n_s", "overlap"])
    if tally:
        sums = np.stack(list(tally.values()))
        yield pa.RecordBatch.from_arrays([pa.array(list(tally), pa.int32()), *(pa.array(sums[:, k]) for k in range(3))], names=["n", "candidates", "kept", "similar"])


def _distance(a: np.ndarray, b: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    out = np.zeros(len(i), np.int64)
    for k in range(a.shape[1]):
        out += np.bitwise_count(a[i, k] ^ b[j, k])
    return out


def _pack(words: tuple[str, ...], singles: int):
    """Tokens as differences, low and high halves apart; tokens of one set only are dropped (they come first)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists = batch.column("toks")
            off, flat = lists.offsets.to_numpy().astype(np.int64), lists.values.to_numpy(zero_copy_only=False).astype(np.int64)
            rows = np.repeat(np.arange(len(lists)), np.diff(off))
            flat = flat[off[0] : off[-1]]
            keep = flat >= singles
            flat, rows = flat[keep], rows[keep]
            sizes = np.bincount(rows, minlength=len(lists))
            step = np.diff(flat, prepend=0)
            starts = np.cumsum(sizes) - sizes
            full = sizes > 0
            step[starts[full]] = flat[starts[full]]
            ends = np.concatenate([[0], np.cumsum(sizes * 2)]).astype(np.int32)
            half = lambda x: pa.Array.from_buffers(pa.binary(), len(lists), [None, pa.py_buffer(ends), pa.py_buffer(x.astype(np.uint16).tobytes())])  # noqa: B023, E731
            names = ["block", "sid", "n", *words]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in names), half(step & 0xFFFF), half(step >> 16)], names=[*names, "lo", "hi"])

    return run


def plan(sets: DataFrame, spec: SimSpec, block_tokens: int | None = None) -> tuple[list[int], list[int], list[tuple[int, int, bool]]]:
    """Size cuts, blocks per size range, and cells ``(i, j, both directions)``."""
    total = sets.agg(F.sum(F.col("n").cast("long") + 8)).first()[0] or 0
    room = block_tokens or max(200_000, min(BLOCK_TOKENS, total // 6))
    # size ranges of about one block each; sets per size are few rows
    sizes = sorted((r["n"], r["c"]) for r in sets.groupBy("n").agg(F.count("*").alias("c")).collect())
    cuts, tokens, held = [], [], 0
    for n, c in sizes:
        if held and held + (n + 8) * c > room:
            cuts.append(n - 1)
            tokens.append(held)
            held = 0
        held += (n + 8) * c
    tokens.append(held)
    parts = [max(1, -(-t // room)) for t in tokens]
    lows, highs = [0, *[c + 1 for c in cuts]], [*cuts, None]
    blocks = [(k, h) for k in range(len(lows)) for h in range(parts[k])]

    def fits(small: int, large: int) -> bool:
        if small == large or highs[small] is None:
            return True
        top = spec.largest_partner(highs[small])
        return top is None or top >= lows[large]

    return cuts, parts, [(i, j, a == b and i != j) for i, (a, _) in enumerate(blocks) for j, (b, _) in enumerate(blocks) if i >= j and fits(b, a)]


def blocks_key(bitmap: BitmapSpec | None) -> tuple:
    """Joins of a collection with equal keys share their blocks."""
    return ("blocks", *((bitmap.variant, bitmap.b, bitmap.hash) if bitmap else ()))


def cell_join(sets: DataFrame, rule: Rule, *, singles: int = 0, block_tokens: int | None = None, kept: Callable | None = None) -> DataFrame:
    """Accepted pairs of a self-join with their overlaps, or counts per size of the larger set.

    ``kept(make)`` gives the written blocks that ``make()`` makes, or those that it made before.
    """
    cuts, parts, cells = plan(sets, rule.spec, block_tokens)
    spark, words = sets.sparkSession, rule.words
    firsts = np.concatenate([[0], np.cumsum(parts)]).tolist()
    bucket = sum(((F.col("n") > c).cast("int") for c in cuts), F.lit(0))
    pick = lambda values: F.element_at(F.array(*[F.lit(int(v)) for v in values]), F.col("__b") + 1)
    blocked = sets.withColumn("__b", bucket).withColumn("block", (pick(firsts[:-1]) + F.pmod(F.xxhash64("sid"), pick(parts))).cast("int"))
    columns = ["block", "sid", "n", *words]
    schema = "block int, sid long, n int, " + "".join(f"{w} long, " for w in words) + "lo binary, hi binary"
    packed = blocked.select(*columns, "toks").mapInArrow(_pack(words, singles), schema)
    # a cell on the diagonal holds its block once
    grid = [(c, k, side, twice) for c, (i, j, twice) in enumerate(cells) for side, k in ((0, i), (1, j))[: 1 + (i != j)]]
    held = ["sid", "n", *words, "lo", "hi"]
    if len(cells) <= READ_CELLS:
        def write() -> dict[int, list[str]]:
            """Files by block: one scan each, blocks without a set have none."""
            made = Scratch(spark, "cells").save(packed.repartitionById(sum(parts), "block"), "blocks", codec="zstd", by="block")
            files: dict[int, list[str]] = {}
            for f in made.inputFiles():
                files.setdefault(int(re.search(r"/block=(\d+)/[^/]*$", f)[1]), []).append(f)
            return files

        files = kept(write) if kept else write()
        read = lambda k: spark.read.schema(packed.select(*held).schema).parquet(*files[k])
        sides = {}
        for c, k, side, twice in grid:
            if k in files:
                sides.setdefault(c, []).append(read(k).select(F.lit(c).alias("cell"), F.lit(side).alias("side"), F.lit(twice).alias("twice"), *held))
        # a union of single partitions only would be one partition; this one has none
        nothing = spark.range(0, 0, 1, 2).select(F.lit(0).alias("cell"), F.lit(0).alias("side"), F.lit(False).alias("twice"), *[F.lit(None).cast(packed.schema[c].dataType).alias(c) for c in held])
        placed = reduce(DataFrame.union, [nothing, *[reduce(DataFrame.union, x).coalesce(1) for x in sides.values()]])
    else:
        placed = packed.join(F.broadcast(spark.createDataFrame(grid, "cell int, block int, side int, twice boolean")), "block")
        placed = placed.select("cell", "side", "twice", *held).repartitionById(max(1, len(cells)), "cell").sortWithinPartitions("cell", "side")

    def join(table: pa.Table) -> Iterator[pa.RecordBatch]:
        side = table.column("side").to_numpy()
        twice = bool(table.column("twice")[0].as_py())
        x = Block(table.filter(pa.array(side == 0)), words) if (side == 0).any() else None
        y = Block(table.filter(pa.array(side == 1)), words) if (side == 1).any() else None
        if x is None or (y is None and any(i != j for i, j, _ in [cells[table.column("cell")[0].as_py()]])):
            return
        y = x if y is None else y
        mark = np.zeros(int(max(x.tok.max(initial=0), y.tok.max(initial=0))) + 1, np.uint8)
        long_ = rule.verify and x.n.mean() > 24 and not (rule.all_pairs and rule.words and rule.limit is None)
        own = x.parity() if long_ else None
        other = own if y is x else y.parity() if long_ else None
        yield from work(x, y, rule, mark, (own, other) if long_ else None)
        if twice:
            yield from work(y, x, rule, mark, (other, own) if long_ else None)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        for batch in batches:
            while batch.num_rows:
                cell = batch.column("cell").to_numpy()
                if held and held[0].column("cell")[0].as_py() != cell[0]:
                    yield from join(pa.Table.from_batches(held))
                    held = []
                end = int(np.searchsorted(cell, cell[0], "right"))
                held.append(batch.slice(0, end))
                batch = batch.slice(end)
        if held:
            yield from join(pa.Table.from_batches(held))

    return placed.mapInArrow(run, COUNT_SCHEMA if rule.counts else PAIR_SCHEMA)


def rule_of(method: str, spec: SimSpec, *, ell: int | None = None, bitmap: BitmapSpec | None = None, limit: int | None = None, **more) -> Rule:
    """The rule of a join method."""
    return Rule(spec, ell if method == "ell_prefix" else None, method in ("prefix_positional", "grouped_prefix"), tuple(bitmap.columns) if bitmap else (), limit, all_pairs=method == "block", **more)


def pays(sets: DataFrame, spec: SimSpec, *, ell: int = 1, singles: int = 0, all_pairs: bool = False, least_pairs: int = 100_000) -> bool:
    """Whether cells write less than a token join: its meetings carry two token arrays each, cells send sets once per cell.

    Both are estimated before any join: meetings by the frequencies of prefix tokens, cells by the plan.
    """
    sizes = sets.agg(F.count("*").alias("c"), F.sum(F.col("n").cast("long")).alias("t")).first()
    count, total = sizes["c"], sizes["t"] or 0
    if all_pairs:
        if count > MOST_SETS:
            return False  # the block join refuses them
        met = count * (count - 1) / 2
    else:
        per = prefix_postings(sets, spec, ell=ell, singles=singles).groupBy("rank").agg(F.count("*").cast("double").alias("c"))
        met = per.agg(F.sum(F.col("c") * (F.col("c") - 1) / 2)).first()[0] or 0.0
        met = min(met, count * (count - 1) / 2)
    if met < least_pairs:
        return False
    cuts, parts, cells = plan(sets, spec)
    sent = (2 * total + 20 * count) / sum(parts) * sum(1 + (i != j) for i, j, _ in cells)
    return sent < met * (24 + 8 * total / max(1, count)) / 4
