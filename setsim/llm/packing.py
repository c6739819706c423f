"""Harmonic packing of token sequences.

Class k holds pieces longer than capacity/(k+1) and not longer than capacity/k; a bin of class k takes exactly k of
them, so every worker fills its bins without knowing any other. The last class holds all shorter pieces; its bins are
filled by next fit, until a piece does not fit. Documents are cut into full sequences and a rest. A
rest that would waste more than ``waste`` of its class's slot is cut again: a piece as long as a slot of the next
class goes there, what remains is classed anew. Bins that a worker leaves unfinished (less than one sequence per
class) meet those of ``GROUP`` neighbouring workers, are filled by class in the same way, and the last few by first
fit in order of decreasing length. Two passes, no sorting, one shuffle of the unfinished bins only: less than
``CLASSES`` sequences a worker, so a group holds at most ``GROUP * CLASSES * capacity`` ids whatever the input.

Defined results: null and empty texts are the end id alone; every id lies in exactly one piece; repeated rows and
null ids are packed like any other row; an empty table gives no sequences. Sequence ids are unique, not gapless.
"""

from __future__ import annotations

import struct
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setsim.llm.columns import release_memory, text_slices
from setsim.llm.tokens import default_tokenizer, encoder
from setsim.scratch import Scratch

CAPACITY, CLASSES, WASTE, GROUP = 1024, 64, 1 / 16, 64
_PIECE = "doc_id long, start long, length long, ids binary, doc_tokens long, class int, sequence_id long, offset long, worker long"
_NAMES = [x.split()[0] for x in _PIECE.split(", ")]


def class_of(n: int, capacity: int = CAPACITY, classes: int = CLASSES) -> int:
    return min(classes, capacity // n)


def cuts(n: int, capacity: int = CAPACITY, classes: int = CLASSES, waste: float = WASTE) -> list[tuple[int, int, int]]:
    """Pieces (start, length, class) of a document of ``n`` ids."""
    out = [(s, capacity, 1) for s in range(0, n - n % capacity, capacity)]
    at = n - n % capacity
    while at < n:
        rest = n - at
        k = class_of(rest, capacity, classes)
        if k < classes and rest < (1 - waste) * (capacity // k):
            k += 1
            rest = min(rest, capacity // k)
        out.append((at, rest, k))
        at += rest
    return out


def pack(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", capacity: int = CAPACITY, end_id: int = 0, tokenizer: str | None = None) -> DataFrame:
    """Pieces with their ids (little-endian unsigned 32-bit), sequence and offset."""
    spark = docs.sparkSession
    path = tokenizer or default_tokenizer()
    schema = _PIECE.replace("doc_id long", f"doc_id {docs.select(doc_id).dtypes[0][1]}")
    rows = docs.select(F.col(doc_id).alias("doc_id"), F.col(text).cast("binary").alias("t"))
    id_type = "int64"

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc, worker = encoder(path), TaskContext.get().partitionId()
        end = struct.pack("<I", end_id)
        open_bins: dict[int, list] = {}
        made = short = 0  # sequences so far; ids in the open bin of the last class

        def close(k: int) -> Iterator[tuple]:
            nonlocal made
            offset = 0
            for p in open_bins.pop(k):
                yield (*p, worker << 32 | made, offset, worker)
                offset += p[2]
            made += 1

        def batch_of(pieces: list, kind: pa.DataType) -> pa.RecordBatch:
            types = [kind, pa.int64(), pa.int64(), pa.binary(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()]
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(list(zip(*pieces, strict=True)) or [[]] * len(types), types, strict=True)], names=_NAMES)

        kind = pa.type_for_alias(id_type)
        for batch in batches:
            kind = batch.column(0).type
            for part, texts in text_slices(batch, 1, limit=2 << 20):
                done: list = []
                for key, t in zip(part.column(0).to_pylist(), texts, strict=True):
                    ids = (enc.ids(t.decode("utf-8", "replace")) if t else b"") + end
                    n = len(ids) >> 2
                    for start, length, k in cuts(n, capacity):
                        if k == CLASSES:
                            if short + length > capacity:
                                done += close(k)
                                short = 0
                            short += length
                        bin_ = open_bins.setdefault(k, [])
                        bin_.append((key, start, length, ids[4 * start : 4 * (start + length)], n, k))
                        if len(bin_) == k < CLASSES:
                            done += close(k)
                if done:
                    yield batch_of(done, kind)
        if left := [(*p, None, None, worker) for bin_ in open_bins.values() for p in bin_]:
            yield batch_of(left, kind)
        open_bins.clear()
        release_memory()

    pieces = Scratch(spark, "packing").save(rows.mapInArrow(work, schema), "pieces")

    def finish(table: pa.Table) -> pa.Table:
        # sequences and offsets are worked out on three numbers a piece; the ids stay where they are
        klass, lengths, workers, starts = (table.column(c).to_numpy() for c in ("class", "length", "worker", "start"))
        sequences: list[list[int]] = []
        open_: dict[int, list[int]] = {}
        short = 0
        for r in np.lexsort((starts, workers, -lengths, klass)).tolist():
            k, n = int(klass[r]), int(lengths[r])
            if k == CLASSES:
                if short + n > capacity:
                    sequences.append(open_.pop(k))
                    short = 0
                short += n
            bin_ = open_.setdefault(k, [])
            bin_.append(r)
            if len(bin_) == k < CLASSES:
                sequences.append(open_.pop(k))
        room: list[list] = []  # first fit for less than one bin of each class
        for r in sorted((r for bin_ in open_.values() for r in bin_), key=lambda r: -lengths[r]):
            n = int(lengths[r])
            slot = next((x for x in room if x[0] >= n), None)
            if slot is None:
                slot = [capacity, []]
                room.append(slot)
            slot[0] -= n
            slot[1].append(r)
        sequences += [members for _, members in room]
        base = 1 << 62 | int(workers[0]) // GROUP << 32
        sequence, offset = np.zeros(len(klass), np.int64), np.zeros(len(klass), np.int64)
        for i, members in enumerate(sequences):
            sequence[members] = base | i
            offset[members] = np.concatenate([[0], lengths[members[:-1]].cumsum()])
        for name, values in (("sequence_id", sequence), ("offset", offset)):
            table = table.set_column(table.schema.get_field_index(name), name, pa.array(values))
        release_memory()
        return table

    filled = pieces.filter("sequence_id IS NOT NULL")
    rest = pieces.filter("sequence_id IS NULL").groupBy((F.col("worker") / GROUP).cast("long").alias("g")).applyInArrow(finish, pieces.schema)
    return filled.unionByName(rest).drop("worker")


def op8_packing(spark, sf_dir: str) -> DataFrame:
    """Contract of operator 8 over whole ``documents``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return digest(pack(docs))


def digest(pieces: DataFrame) -> DataFrame:
    return pieces.select("doc_id", "start", "length", F.crc32("ids").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset")
