"""Language identification by cross-parsing entropy.

Per language a suffix automaton of labelled text is built. A text is parsed greedily into the longest phrases that
occur in a language's text; a language that needs few phrases per byte predicts the text well. The automaton's
transitions are stored as one dense table in which a missing transition already points to the state after a restart
at the root and carries a flag, so parsing is one table lookup per byte; many segments of many texts advance together.
Whole texts are parsed, in segments of ``SEGMENT`` bytes (a cut adds at most one phrase per segment and language).

Training text is a bounded sample: about ``train_bytes`` bytes per learned language, from all allowed rows drawn by id
hash, of each a span of at most ``span_bytes`` bytes that begins anywhere in the text (by hash). Every byte value that
occurs in it has a symbol of its own; a language with less training text than others is learnt from what it has. A
score is the best language's share of the odds, e to the phrases saved over at most ``ODDS_BYTES`` bytes. Defined results: null texts and texts without any letter give ``und`` with score 0; ties go to the language
first in byte order; without any training text every prediction is ``und``.
"""

from __future__ import annotations

from collections import defaultdict

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setsim.llm.columns import text_column

TRAIN_BYTES, SPAN_BYTES, SEGMENT, ODDS_BYTES = 48_000, 8_000, 512, 400
_UNKNOWN, _PAD, _SPACE = 0, 1, 2
_RESTART = np.int32(-(2**31))


def _fold() -> np.ndarray:
    """Bytes to letters: A-Z lower-cased, other ASCII to a space."""
    fold = np.full(256, 32, np.uint8)
    fold[97:123] = np.arange(97, 123)
    fold[65:91] = np.arange(97, 123)
    fold[128:] = np.arange(128, 256)
    return fold


class SuffixAutomaton:
    """All substrings of a symbol sequence, one state per class of end positions."""

    def __init__(self, symbols: list[int]):
        self.next: list[dict[int, int]] = [{}]
        link, length, last = [-1], [0], 0
        for c in symbols:
            cur = len(self.next)
            self.next.append({})
            length.append(length[last] + 1)
            link.append(0)
            p = last
            while p >= 0 and c not in self.next[p]:
                self.next[p][c] = cur
                p = link[p]
            if p >= 0:
                q = self.next[p][c]
                if length[p] + 1 == length[q]:
                    link[cur] = q
                else:
                    twin = len(self.next)
                    self.next.append(dict(self.next[q]))
                    length.append(length[p] + 1)
                    link.append(link[q])
                    while p >= 0 and self.next[p].get(c) == q:
                        self.next[p][c] = twin
                        p = link[p]
                    link[q] = link[cur] = twin
            last = cur

    def table(self, alphabet: int) -> np.ndarray:
        """Dense transitions; the sign bit marks that a phrase starts. The last row is the state before any phrase."""
        begin = len(self.next)
        root = np.full(alphabet, np.int32(begin) | _RESTART, np.int32)  # a symbol that never occurs is a phrase of its own
        for c, s in self.next[0].items():
            root[c] = s | _RESTART
        t = np.tile(root, (begin + 1, 1))
        for s, out in enumerate(self.next):
            for c, to in out.items():
                t[s, c] = to
        t[:, _PAD] = np.arange(begin + 1, dtype=np.int32)
        return (t & np.int32(2**31 - 1)) * alphabet | (t & _RESTART)  # states come multiplied by the row width


class CrossParser:
    """Automata of several languages over one alphabet."""

    def __init__(self, texts: dict[str, bytes]):
        self.langs = sorted(texts)
        fold = _fold()
        folded = {k: fold[np.frombuffer(v, np.uint8)] for k, v in texts.items()}
        counts = sum((np.bincount(v, minlength=256) for v in folded.values()), np.zeros(256, np.int64))
        counts[32] = 0
        used = [int(c) for c in np.flatnonzero(counts)]
        self.width = 3 + len(used)
        code = np.full(256, _UNKNOWN, np.uint8)
        code[32] = _SPACE
        code[used] = np.arange(3, 3 + len(used))
        self.code = code[fold]
        self.tables = [SuffixAutomaton(code[folded[k]].tolist()).table(self.width).ravel() for k in self.langs]

    def phrases(self, texts: list[bytes]) -> np.ndarray:
        """Phrases per text and language."""
        owner, starts, sizes = [], [], []
        at = 0
        for i, t in enumerate(texts):
            for a in range(0, len(t), SEGMENT):
                owner.append(i)
                starts.append(at + a)
                sizes.append(min(SEGMENT, len(t) - a))
            at += len(t)
        out = np.zeros((len(texts), len(self.langs)))
        if not owner:
            return out
        symbols = np.concatenate([self.code[np.frombuffer(b"".join(texts), np.uint8)], np.full(SEGMENT, _PAD, np.uint8)])
        who, sizes = np.array(owner), np.array(sizes)
        steps = np.array(starts)[None, :] + np.arange(int(sizes.max()))[:, None]
        lanes = symbols[steps]
        lanes[np.arange(len(lanes))[:, None] >= sizes[None, :]] = _PAD
        for k, table in enumerate(self.tables):
            state = np.full(len(who), len(table) - self.width, np.int32)
            begun = np.zeros(len(who), np.int32)
            for row in lanes:
                np.take(table, state + row, out=state)
                begun -= state >> 31
                state &= 2**31 - 1
            out[:, k] = np.bincount(who, begun, len(texts))
        return out

    def predict(self, texts: list[bytes | None]) -> list[dict]:
        kept = [t if t is not None and self.langs and has_letter(t) else b"" for t in texts]
        rate = self.phrases(kept) / np.maximum(1, [len(t) for t in kept])[:, None] if self.langs else np.zeros((len(kept), 0))
        result = []
        for t, r in zip(kept, rate, strict=True):
            if not t:
                result.append({"lang": "und", "score": 0.0})
                continue
            k = int(r.argmin())
            odds = np.exp((r[k] - r) * min(len(t), ODDS_BYTES))
            result.append({"lang": self.langs[k], "score": float(1 / odds.sum())})
        return result


_ASCII_LETTERS = bytes(range(65, 91)) + bytes(range(97, 123))


def has_letter(text: bytes) -> bool:
    """Whether any character is a letter."""
    return len(text.translate(None, _ASCII_LETTERS)) < len(text) or any(c.isalpha() for c in text.decode("utf-8", "replace") if c > "\x7f")


def held_out(doc_id: str = "doc_id", folds: int = 4, fold: int = 2):
    """Whether crc32 of the id as text falls into the fold (a null id is not held out)."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % folds == fold, F.lit(False))


def training_texts(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", lang: str = "lang", train_bytes: int = TRAIN_BYTES, span_bytes: int = SPAN_BYTES) -> dict[str, bytes]:
    """A bounded sample of labelled text per language, from rows outside the held-out fold."""
    rows = docs.select(F.col(doc_id).alias("k"), F.col(text).cast("binary").alias("t"), F.col(lang).alias("lang")).filter(F.col("lang").isNotNull() & F.col("t").isNotNull() & ~held_out("k"))
    used = F.least(F.length("t"), F.lit(span_bytes))
    totals = {r.lang: r.n for r in rows.groupBy("lang").agg(F.sum(used).alias("n")).collect() if r.n}
    if not totals:
        return {}
    # at most `share` of each language is read on the driver: in expectation three times what is used
    share = F.create_map(*[F.lit(x) for k, n in totals.items() for x in (k, min(1.0, 3 * train_bytes / n))])
    order = F.pmod(F.xxhash64("k", "t"), F.lit(1 << 30))
    start = (F.pmod(F.xxhash64("t", "k"), F.greatest(F.length("t") - span_bytes + 1, F.lit(1))) + 1).cast("int")
    picked = rows.withColumn("o", order).filter(F.col("o") < share[F.col("lang")] * (1 << 30)).select("lang", "o", F.substring("t", start, F.lit(span_bytes)).alias("t"))
    by_lang: dict[str, list] = defaultdict(list)
    for r in picked.collect():
        by_lang[r.lang].append((r.o, bytes(r.t)))
    return {k: b" ".join(t for _, t in sorted(v))[:train_bytes] for k, v in by_lang.items()}


_PARSERS: dict[int, CrossParser] = {}


def language_column(spark, texts: dict[str, bytes], text: str = "text"):
    """``struct<lang, score>`` of a text column."""
    shared = spark.sparkContext.broadcast(texts)

    def setup():
        from setsim.llm import language  # the worker's own module keeps the automata between tasks

        key = hash(tuple(sorted(shared.value.items())))
        if key not in language._PARSERS:
            language._PARSERS.clear()
            language._PARSERS[key] = language.CrossParser(shared.value)
        return language._PARSERS[key].predict

    return text_column(setup, "struct<lang:string,score:double>", text)


def op6_language(spark, sf_dir: str) -> DataFrame:
    """Contract of operator 6 over whole ``documents``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "lang")
    guess = docs.select("doc_id", language_column(spark, training_texts(docs)).alias("g"))
    return guess.select("doc_id", held_out().alias("held_out"), F.col("g.lang").alias("lang_pred"), "g.score")
