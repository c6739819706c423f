"""Quality classifier: a generalised additive model with pairwise interactions.

Every text becomes a fixed vector of surface statistics of the *whole* text. Each feature is cut into quantile bins.
Training boosts in cycles: one shallow tree (at most ``LEAVES`` leaves over the bins of one feature) per feature and
round, each a small Newton step on the logistic loss, added to that feature's lookup table. The feature pairs whose
residuals gain most from a four-cell cut then get tables of their own, boosted in the same cyclic way. A score is the
logistic of the intercept plus one table entry per feature and pair: vectorised additions of bins.

The model is fitted on the driver from at most ``sample_rows`` labels (those of the least hash of their id) and
``REPEATS`` times as many documents (ids may repeat); scores cover all rows. Defined results: null and empty texts have the vector of an empty text and get a
score; repeated rows are scored alike; rows without a label, or with a null one, are not learnt from; without any
usable label every score is ``prior``.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setsim.llm.columns import free_name, text_column

SAMPLE_ROWS, BINS, LEAVES, ROUNDS, RATE, PAIRS, PAIR_ROUNDS, REPEATS = 20_000, 32, 4, 120, 0.15, 8, 60, 2

FEATURES = (
    "log_chars", "log_words", "word_length", "upper", "digits", "ascii_marks", "odd_marks", "bars", "non_ascii", "line_breaks",
    "distinct_words", "top_word", "distinct_lines", "repeated_line_bytes", "log_longest_line", "short_words", "long_words",
    "marked_words", "commas", "full_stops", "repeated_pairs",
)
_ODD = np.array([c in b"#$%&*+<=>@\\^_`{}~!" for c in range(256)])
_MARKS = np.array([33 <= c <= 47 or 58 <= c <= 64 or 91 <= c <= 96 or 123 <= c <= 126 for c in range(256)])


def features_of(text: bytes | None) -> list[float]:
    """Surface statistics of one whole text, in the order of ``FEATURES``."""
    text = text or b""
    counts = np.bincount(np.frombuffer(text, np.uint8), minlength=256)
    n = max(1, len(text))
    words = text.split()
    lines = [x for x in text.split(b"\n") if x]
    m = max(1, len(words))
    kinds: dict[bytes, int] = {}
    for w in words:
        kinds[w] = kinds.get(w, 0) + 1
    seen: set[bytes] = set()
    again = 0
    for x in lines:
        again += len(x) if x in seen else 0
        seen.add(x)
    lengths = np.fromiter(map(len, words), np.int32, len(words))
    pairs = len(set(zip(words, words[1:]))) if len(words) > 1 else 0  # noqa: B905
    letters = max(1, int(counts[65:91].sum() + counts[97:123].sum()))
    return [
        float(np.log1p(len(text))), float(np.log1p(len(words))), float(lengths.mean()) if len(words) else 0.0, counts[65:91].sum() / letters, counts[48:58].sum() / n,
        counts[_MARKS].sum() / n, counts[_ODD].sum() / n, counts[124] / m, counts[128:].sum() / n, counts[10] / m,
        len(kinds) / m, max(kinds.values(), default=0) / m, len(seen) / max(1, len(lines)), again / n, float(np.log1p(max(map(len, lines), default=0))), float((lengths <= 3).sum()) / m, float((lengths > 12).sum()) / m,
        sum(1 for w in words if w[-1] < 48 and w[-1] not in b",.") / m, counts[44] / m, counts[46] / m, 1 - pairs / max(1, len(words) - 1),
    ]


@dataclass
class AdditiveModel:
    """Bin edges and lookup tables; ``raw`` adds table entries, ``score`` is their logistic."""

    edges: list[np.ndarray]
    tables: list[np.ndarray]
    pairs: list[tuple[int, int]] = field(default_factory=list)
    pair_tables: list[np.ndarray] = field(default_factory=list)
    intercept: float = 0.0

    def bins(self, x: np.ndarray) -> np.ndarray:
        return np.stack([np.searchsorted(e, x[:, j], side="right") for j, e in enumerate(self.edges)], 1) if len(x) else np.zeros((0, len(self.edges)), int)

    def raw(self, x: np.ndarray) -> np.ndarray:
        b = self.bins(x)
        out = np.full(len(x), self.intercept)
        for j, t in enumerate(self.tables):
            out += t[b[:, j]]
        for (i, j), t in zip(self.pairs, self.pair_tables, strict=True):
            out += t[b[:, i], b[:, j]]
        return out

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.raw(x), -30, 30)))


def _gain(g: np.ndarray, h: np.ndarray) -> np.ndarray:
    return g * g / (h + 1.0)


def _tree(g: np.ndarray, h: np.ndarray, leaves: int) -> np.ndarray:
    """Newton step per bin of a tree with few leaves, grown best split first over ordered bins."""
    cg, ch = np.concatenate([[0], g.cumsum()]), np.concatenate([[0], h.cumsum()])

    def best(a: int, b: int) -> tuple[float, int]:
        if b - a < 2:
            return 0.0, a
        cut = np.arange(a + 1, b)
        left, right = (cg[cut] - cg[a], ch[cut] - ch[a]), (cg[b] - cg[cut], ch[b] - ch[cut])
        won = _gain(*left) + _gain(*right) - _gain(cg[b] - cg[a], ch[b] - ch[a])
        k = int(won.argmax())
        return float(won[k]), int(cut[k])

    parts = [(0, len(g))]
    while len(parts) < leaves:
        (won, cut), (a, b) = max(((best(*p), p) for p in parts), key=lambda x: x[0][0])
        if won <= 1e-9:
            break
        parts.remove((a, b))
        parts += [(a, cut), (cut, b)]
    step = np.zeros(len(g))
    for a, b in parts:
        step[a:b] = (cg[b] - cg[a]) / (ch[b] - ch[a] + 1.0)
    return step


def fit(x: np.ndarray, y: np.ndarray, *, rounds: int = ROUNDS, pair_rounds: int = PAIR_ROUNDS, n_pairs: int = PAIRS, prior: float = 0.5) -> AdditiveModel:
    """Cyclic boosting of the one-feature tables, then of the best pairs."""
    d = len(FEATURES)
    if len(y) == 0 or y.min() == y.max():
        p = prior if len(y) == 0 else (y.sum() + 1) / (len(y) + 2)
        return AdditiveModel([np.zeros(0)] * d, [np.zeros(1)] * d, intercept=float(np.log(p / (1 - p))))
    edges = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, BINS + 1)[1:-1])) for j in range(d)]
    m = AdditiveModel(edges, [np.zeros(len(e) + 1) for e in edges], intercept=float(np.log(y.mean() / (1 - y.mean()))))
    b = m.bins(x)
    raw = np.full(len(y), m.intercept)
    for _ in range(rounds):
        for j, table in enumerate(m.tables):
            p = 1 / (1 + np.exp(-raw))
            step = RATE * _tree(np.bincount(b[:, j], y - p, len(table)), np.bincount(b[:, j], p * (1 - p), len(table)), LEAVES)
            table += step
            raw += step[b[:, j]]
    p = 1 / (1 + np.exp(-raw))
    g, h = y - p, p * (1 - p)

    def cells(i: int, j: int, v: np.ndarray) -> np.ndarray:
        shape = (len(m.tables[i]), len(m.tables[j]))
        return np.bincount(b[:, i] * shape[1] + b[:, j], v, shape[0] * shape[1]).reshape(shape)

    def pair_gain(i: int, j: int) -> float:
        cg, ch = (np.pad(cells(i, j, v), ((1, 0), (1, 0))).cumsum(0).cumsum(1) for v in (g, h))
        parts = [(c[:-1, :-1], c[:-1, -1:] - c[:-1, :-1], c[-1:, :-1] - c[:-1, :-1], c[-1, -1] - c[:-1, -1:] - c[-1:, :-1] + c[:-1, :-1]) for c in (cg, ch)]
        return float(sum(_gain(*q) for q in zip(*parts, strict=True)).max())

    ranked = sorted(((pair_gain(i, j), i, j) for i in range(d) for j in range(i + 1, d)), reverse=True)
    m.pairs = [(i, j) for _, i, j in ranked[:n_pairs]]
    m.pair_tables = [np.zeros((len(m.tables[i]), len(m.tables[j]))) for i, j in m.pairs]
    for _ in range(pair_rounds):
        for (i, j), table in zip(m.pairs, m.pair_tables, strict=True):
            p = 1 / (1 + np.exp(-raw))
            cg, ch = cells(i, j, y - p), cells(i, j, p * (1 - p))
            half = _tree(cg.sum(1), ch.sum(1), 2)  # one cut of the first feature, then one of the second on either side
            cut = int(np.flatnonzero(np.diff(half))[0]) + 1 if np.ptp(half) > 0 else len(half)
            step = np.zeros_like(table)
            for rows in (slice(0, cut), slice(cut, None)):
                step[rows] = RATE * _tree(cg[rows].sum(0), ch[rows].sum(0), 2)
            table += step
            raw += step[b[:, i], b[:, j]]
    return m


def held_out(doc_id: str = "doc_id", folds: int = 5, fold: int = 0):
    """Whether crc32 of the id as text falls into the fold (a null id is not held out)."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % folds == fold, F.lit(False))


def train(docs: DataFrame, labels: DataFrame, *, doc_id: str = "doc_id", text: str = "text", label: str = "quality", sample_rows: int = SAMPLE_ROWS, **options) -> AdditiveModel:
    """Fit on a bounded sample of labelled rows outside the held-out fold."""
    known = labels.select(F.col(doc_id).alias("k"), F.col(label).cast("double").alias("y")).filter(F.col("k").isNotNull() & F.col("y").isNotNull() & ~held_out("k"))
    known = known.orderBy(F.xxhash64("k"), "k", "y").limit(sample_rows)
    rows = docs.select(F.col(doc_id).alias("k"), F.col(text).alias("t")).join(F.broadcast(known), "k")  # at most sample_rows small rows
    rows = rows.select("k", "y", text_column(lambda: lambda texts: [features_of(t) for t in texts], "array<double>", "t").alias("x"))
    got = rows.orderBy(F.xxhash64("k"), "k", "y").limit(REPEATS * sample_rows).toPandas()
    x = np.array(got.x.tolist(), float).reshape(-1, len(FEATURES))
    return fit(x, got.y.to_numpy(float), **options)


def quality_scores(docs: DataFrame, model: AdditiveModel, *, text: str = "text", out: str = "score") -> DataFrame:
    """All rows and columns of ``docs`` plus ``out``, the probability of label 1."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def setup():
        return lambda texts: shared.value.score(np.array([features_of(t) for t in texts], float).reshape(-1, len(FEATURES))).tolist()

    return docs.withColumn(out, text_column(setup, "double", text))


def keep_good(docs: DataFrame, labels: DataFrame, *, threshold: float = 0.3, **options) -> DataFrame:
    """Rows whose score reaches the threshold; columns unchanged."""
    out = free_name(docs, "__quality")
    return quality_scores(docs, train(docs, labels, **options), out=out).filter(F.col(out) >= threshold).drop(out)


def op5_quality(spark, sf_dir: str) -> DataFrame:
    """Contract of operator 5 over whole ``documents``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    model = train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    scored = quality_scores(docs, model)
    return scored.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))
