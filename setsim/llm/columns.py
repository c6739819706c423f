"""Arrow-batched columns: a whole-text Python function as a Column, set up once per task."""

from __future__ import annotations

import contextlib
import ctypes
import gc
from collections.abc import Callable, Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type
from pyspark.sql.types import _parse_datatype_string

#: Rows and bytes that a batch function sees at once, whatever the session's Arrow batch size.
BATCH_ROWS, BATCH_BYTES = 2048, 8 << 20


def arrow_kind(ddl: str) -> pa.DataType:
    return to_arrow_type(_parse_datatype_string(ddl))


def slices(sizes: list[int], rows: int = BATCH_ROWS, limit: int = BATCH_BYTES) -> Iterator[tuple[int, int]]:
    """Consecutive ranges of at most ``rows`` rows and about ``limit`` bytes (one row at least)."""
    begin = total = 0
    for i, n in enumerate(sizes):
        if i > begin and (i - begin >= rows or total + n > limit):
            yield begin, i
            begin, total = i, 0
        total += n
    if begin < len(sizes):
        yield begin, len(sizes)


def free_name(df: DataFrame, base: str) -> str:
    """A column name that ``df`` does not use."""
    while base in df.columns:
        base += "_"
    return base


def text_slices(batch: pa.RecordBatch, column: int, rows: int = BATCH_ROWS, limit: int = BATCH_BYTES) -> Iterator[tuple[pa.RecordBatch, list]]:
    """Parts of a batch with their texts as Python bytes; only one part's texts exist at a time."""
    sizes = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_pylist()
    for a, b in slices(sizes, rows, limit):
        part = batch.slice(a, b - a)
        yield part, part.column(column).to_pylist()


def release_memory() -> None:
    """Give freed memory back to the system at the end of a task.

    Spark keeps idle Python workers for a while; without this they would hold the buffers of their last task beside
    those of the workers of the next stage.
    """
    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # other systems' C libraries have no such call
        ctypes.CDLL(None).malloc_trim(0)


def text_column(setup: Callable[[], Callable[[list], list]], ddl: str, text: str | Column) -> Column:
    """Column of ``setup()(list of UTF-8 bytes or None)``; not re-evaluated by filters on it."""
    kind = arrow_kind(ddl)
    col = F.col(text) if isinstance(text, str) else text

    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        work = setup()
        for batch in batches:
            if not len(batch):
                yield pa.array([], kind)
            for _, texts in text_slices(pa.RecordBatch.from_arrays([batch], names=["t"]), 0):
                yield pa.array(work(texts), kind)  # Spark counts rows, not batches: a slice's results leave at once
        del work
        release_memory()

    return F.arrow_udf(run, _parse_datatype_string(ddl)).asNondeterministic()(col.cast("binary"))
