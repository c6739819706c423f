"""Token columns: what turns texts, JSON and vectors into arrays of tokens (nulls give no tokens)."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F


def _col(c: str | Column) -> Column:
    return F.col(c) if isinstance(c, str) else c


def words(text: str | Column, pattern: str = r"[^ \t\n\r\f\x0B]+") -> Column:
    """Runs that match ``pattern`` in the lower-cased text."""
    return F.regexp_extract_all(F.lower(_col(text)), F.lit(f"({pattern})"), 1)


def _runs(items: Column, k: int, sep: str) -> Column:
    """Joined runs of ``k`` neighbours: shifted copies zipped, so that no lambda evaluates the array again."""
    n = F.greatest(F.size(items) - (k - 1), F.lit(0))
    out = F.slice(items, F.lit(1), n)
    for j in range(1, k):
        out = F.zip_with(out, F.slice(items, F.lit(j + 1), n), lambda a, b: F.concat(a, F.lit(sep), b))
    return out


def qgrams(text: str | Column, q: int = 2, lower: bool = True) -> Column:
    """All substrings of ``q`` characters, blanks included; a shorter text has none."""
    t = F.lower(_col(text)) if lower else _col(text)
    return _runs(F.regexp_extract_all(t, F.lit("(?s)."), F.lit(0)), q, "")


def _distinct_runs(q: int):
    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for batch in batches:
            found = []
            for text in batch.to_pylist():  # the q code points of a run side by side in one number
                c = np.frombuffer((text or "").encode("utf-32-le"), np.uint32).astype(np.int64)
                n = max(0, len(c) - q + 1)
                found.append(np.unique(sum((c[j : j + n] << 21 * j for j in range(q)), np.zeros(n, np.int64))))
            flat = np.concatenate([np.zeros(0, np.int64), *found])
            chars = np.stack([flat >> 21 * j & 0x1FFFFF for j in range(q)], 1).astype("<u4")
            bytes_ = (1 + (chars > 0x7F) + (chars > 0x7FF) + (chars > 0xFFFF)).sum(1)
            ends = lambda sizes: np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)
            runs = pa.StringArray.from_buffers(len(flat), pa.py_buffer(ends(bytes_)), pa.py_buffer(chars.tobytes().decode("utf-32-le").encode()))
            yield pa.ListArray.from_arrays(pa.array(ends([len(f) for f in found])), runs)

    return run


def distinct_qgrams(text: str | Column, q: int = 2) -> Column:
    """The distinct ``qgrams`` of the lower-cased text (q up to 3), without a lambda per character."""
    if not 1 <= q <= 3:
        raise ValueError("three code points fit into one number")
    return F.arrow_udf(_distinct_runs(q), "array<string>")(F.lower(_col(text)))


def shingles(tokens: Column, k: int = 3) -> Column:
    """Joined runs of ``k`` consecutive tokens."""
    return _runs(tokens, k, " ")


def json_entries(props: str | Column) -> Column:
    """``key=value`` tokens of a flat JSON object."""
    parsed = F.from_json(_col(props), "map<string,string>")
    return F.transform(F.map_entries(parsed), lambda e: F.concat_ws("=", e["key"], e["value"]))


def positive_dimensions(vector: str | Column) -> Column:
    """1-based indices of the positive components, as strings."""
    v = F.transform(_col(vector), lambda x, i: F.when(x > 0, (i + 1).cast("string")))
    return F.filter(v, lambda x: x.isNotNull())
