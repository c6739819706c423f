"""Byte-level BPE token ids per pre-token, and edit-aware token counts.

``PieceEncoder`` gives the ids of a ``tokenizers`` file. Where the file is byte-level BPE with merges ordered by id, its
vocabulary runs in the byte-pair core of ``tiktoken`` (equal ids for every Unicode character; the tests hold both
against each other), and the tokenizer itself is never loaded. Pre-tokens are counted once each in a bounded cache.

``TokenTree`` is a document's segment tree: leaves stand for runs of pre-tokens, nodes hold sums of characters and
tokens. It holds no text and no pre-tokens, so it is stored as one row of integers per document (``token_trees``)
and taken up again when edits come (``apply_edits``): an edit encodes the pre-tokens that go and that come, from
``CONTEXT`` pre-tokens before it until the pre-token borders of old and new text meet again, and updates the sums of
their leaves and above. A leaf takes up to ``FULL`` tokens; only beyond that its
pre-tokens are cut into several leaves, and where these find no room the sums (nothing else) are laid out anew.

Defined results: null texts count as empty; the special token's string is one pre-token of one token; edits are
positions in the original text, applied left to right, and must not overlap (ValueError); edits of an id that no
document has are ignored; rows that repeat an id all get its edits; a null id has no edits.
"""

from __future__ import annotations

import json
import unicodedata
from array import array
from collections.abc import Iterator

import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setsim.llm.columns import free_name, text_column, text_slices
from setsim.scratch import Scratch

# Fixed value: the pattern of byte-level pre-tokenizers.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
SPECIAL = "<|endoftext|>"
CACHE, CONTEXT, LEAF, FULL = 100_000, 3, 64, 256
_PIECES = regex.compile(PATTERN)
_COMMON = regex.compile("[\\x00-\\u02af\\u0370-\\u0377\\u0384-\\u0527\\u2010-\\u2027\\u2030-\\u205e\\u3041-\\u3096\\u4e00-\\u9fa5\\uac00-\\ud7a3]*")


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def _core(path: str):
    """The tokenizer's vocabulary as byte-pair ranks; None where it is not byte-level BPE with merges ordered by id."""
    import tiktoken

    with open(path, encoding="utf-8") as f:
        spec = json.load(f)
    model, split, added = spec["model"], spec.get("pre_tokenizer") or {}, spec.get("added_tokens") or []
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]  # bytes that stand for themselves in such files
    shifted = [b for b in range(256) if b not in set(plain)]
    to_byte = {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(shifted)}
    if spec.get("normalizer") or split.get("type") != "ByteLevel" or split.get("add_prefix_space") or not split.get("use_regex", True) or "merges" not in model:
        return None
    if [x["content"] for x in added] != [SPECIAL] or any(x.get("lstrip") or x.get("rstrip") or x.get("single_word") for x in added):
        return None
    pairs = (m.split(" ") if isinstance(m, str) else m for m in model["merges"])
    if any(model["vocab"].get(a + b) != 256 + i for i, (a, b) in enumerate(pairs)):
        return None
    ranks = {bytes(to_byte[c] for c in token): i for token, i in model["vocab"].items() if token != SPECIAL}
    return tiktoken.Encoding("core", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens={SPECIAL: added[0]["id"]})._core_bpe


class PieceEncoder(dict):
    """Pre-token -> number of its ids; ``ids`` gives a text's ids as little-endian unsigned 32-bit integers."""

    def __init__(self, path: str):
        super().__init__()
        self.path, self.core = path, _core(path)
        self._tokenizer = None

    def __missing__(self, piece: str) -> int:
        if len(self) >= CACHE:
            self.clear()
        n = 1 if piece == SPECIAL else len(self.core.encode_single_piece(piece.encode()))
        if len(piece) <= 64:
            self[piece] = n
        return n

    @property
    def tokenizer(self):
        """The tokenizer itself, loaded when it is first needed."""
        if self._tokenizer is None:
            from tokenizers import Tokenizer

            self._tokenizer = Tokenizer.from_file(self.path)
        return self._tokenizer

    def ids(self, text: str) -> bytes:
        if self.core is None:
            return array("I", self.tokenizer.encode(text, add_special_tokens=False).ids).tobytes()
        return bytes(self.core.encode_to_tiktoken_buffer(text, {SPECIAL}))

    def pieces(self, text: str, at: int = 0) -> Iterator[str]:
        """Pre-tokens from a pre-token border on; what lies before the border has no influence."""
        # characters that newer Unicode versions have assigned are classed by the tokenizer, not by the pattern's engine
        known = _COMMON.match(text, at).end() == len(text) or all(unicodedata.category(c) != "Cn" for c in set(text[at:]))
        while at < len(text):
            stop = text.find(SPECIAL, at)
            stop = len(text) if stop < 0 else stop
            if known:
                for m in _PIECES.finditer(text, at, stop):
                    yield m[0]
            else:
                part = text[at:stop]
                yield from (part[a:b] for _, (a, b) in self.tokenizer.pre_tokenizer.pre_tokenize_str(part))
            if stop < len(text):
                yield SPECIAL
            at = stop + len(SPECIAL)


_ENCODERS: dict[str, PieceEncoder] = {}


def encoder(path: str) -> PieceEncoder:
    """The process's encoder of a tokenizer file; workers keep it between tasks."""
    from setsim.llm import tokens  # the importable module, also when this function came by pickle

    if path not in tokens._ENCODERS:
        tokens._ENCODERS[path] = tokens.PieceEncoder(path)
    return tokens._ENCODERS[path]


class TokenTree:
    """Sums of characters and tokens over runs of a document's pre-tokens, kept under edits.

    ``sums`` is the tree in heap order, as pairs (characters, tokens): the root is entry 1, leaves fill the second half.
    """

    def __init__(self, enc: PieceEncoder, text: str, sums: list[tuple[int, int]] | None = None):
        if enc.core is None:
            raise ValueError("token trees need a byte-level BPE tokenizer with merges ordered by id")
        self.enc, self.text, self.encoded = enc, text, 0
        if sums is None:
            self._lay([self._weigh(x) for x in self._runs(list(enc.pieces(text)), LEAF)])
        else:
            self.sums = sums

    @property
    def width(self) -> int:
        return len(self.sums) // 2

    def tokens(self) -> int:
        return self.sums[1][1]

    @staticmethod
    def _runs(pieces: list[str], size: int) -> list[list[str]]:
        return [pieces[i : i + size] for i in range(0, len(pieces), size)]

    def _weigh(self, pieces: list[str]) -> tuple[int, int]:
        self.encoded += len(pieces)
        return sum(map(len, pieces)), sum(map(self.enc.__getitem__, pieces))

    def _lay(self, leaves: list[tuple[int, int]]) -> None:
        width = 1 << max(0, len(leaves) - 1).bit_length()
        self.sums = [(0, 0)] * width + leaves + [(0, 0)] * (width - len(leaves))
        for i in range(width - 1, 0, -1):
            self._add(i)

    def _add(self, i: int) -> None:
        (a, b), (c, d) = self.sums[2 * i], self.sums[2 * i + 1]
        self.sums[i] = (a + c, b + d)

    def _leaf_at(self, pos: int) -> tuple[int, int]:
        """Leaf that holds the character position (the last one with text beyond the end), and where it begins."""
        i, begin = 1, 0
        while i < self.width:
            i *= 2
            if pos >= begin + self.sums[i][0] and self.sums[i + 1][0]:
                begin += self.sums[i][0]
                i += 1
        return i - self.width, begin

    def _start(self, start: int) -> tuple[int, int, int]:
        """First leaf that an edit at ``start`` touches, where it begins, and the border from which to split anew."""
        leaf, begin = self._leaf_at(max(0, start - 1))
        while True:
            borders, at = [begin], begin
            for p in self.enc.pieces(self.text, begin):
                at += len(p)
                if at > start:
                    break
                borders.append(at)
            # CONTEXT pre-tokens before the position, and as far as a special token's string could reach back
            keep = max(0, len(borders) - 1 - CONTEXT)
            while keep > 0 and borders[keep] > start - len(SPECIAL):
                keep -= 1
            if keep > 0 or begin == 0:
                return leaf, begin, borders[keep]
            leaf, begin = self._leaf_at(begin - 1)

    def edit(self, start: int, end: int, new: str) -> None:
        """Replace characters ``[start, end)`` of the current text."""
        old, shift = self.text, len(new) - (end - start)
        first, begin, at = self._start(start)
        self.text = old[:start] + new + old[end:]
        fresh: list[str] = []
        gone: list[str] = []
        ahead, border = self.enc.pieces(old, at), at  # old pre-tokens, read as far as the new ones are
        met = False
        for p in self.enc.pieces(self.text, at):
            while (border < end or border + shift < at) and (q := next(ahead, None)) is not None:
                gone.append(q)
                border += len(q)
            if border >= end and at == border + shift:
                met = True  # from here on all pre-tokens are the old ones
                break
            fresh.append(p)
            at += len(p)
        if not met:
            gone += ahead
            border = len(old)
        last, past = first, begin + self.sums[self.width + first][0]
        while past < border:
            last += 1
            past += self.sums[self.width + last][0]
        slots, at = last + 1 - first, self.width + first
        leaves = [self._weigh(fresh), *self.sums[at : at + slots]]
        less = self._weigh(gone)
        whole = (sum(a for a, _ in leaves) - less[0], sum(b for _, b in leaves) - less[1])
        if whole[1] <= FULL:
            runs = [whole]
        else:  # too much for one leaf: the touched leaves are cut anew
            pieces, stop = [], begin + whole[0]
            for p in self.enc.pieces(self.text, begin):
                if begin >= stop:
                    break
                pieces.append(p)
                begin += len(p)
            runs = [self._weigh(x) for x in self._runs(pieces, LEAF)]
        if len(runs) > slots:  # no room: the sums of all leaves are laid out anew
            every = self.sums[self.width :]
            self._lay([x for x in every[:first] + runs + every[last + 1 :] if x[0]])
            return
        self.sums[at : at + slots] = runs + [(0, 0)] * (slots - len(runs))
        low, high = at, at + slots - 1
        while low > 1:
            low, high = low // 2, high // 2
            for i in range(low, high + 1):
                self._add(i)


_TREE = "struct<chars:array<int>,tokens:array<int>>"


def token_trees(docs: DataFrame, *, text: str = "text", out: str = "tree", tokenizer: str | None = None) -> DataFrame:
    """All rows and columns of ``docs`` plus ``out``, the sums of the text's token tree (``out.tokens[1]`` is the count)."""
    path = tokenizer or default_tokenizer()

    def setup():
        enc = encoder(path)

        def work(texts: list) -> list:
            trees = (TokenTree(enc, t.decode("utf-8", "replace") if t else "").sums for t in texts)
            return [{"chars": [a for a, _ in s], "tokens": [b for _, b in s]} for s in trees]

        return work

    return docs.withColumn(out, text_column(setup, _TREE, text))


def apply_edits(trees: DataFrame, edits: DataFrame, docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", tokenizer: str | None = None) -> DataFrame:
    """The edited documents: ``doc_id, text_key, text, tree, n_edits, n_reencoded``, repeated rows once.

    ``trees`` holds ``doc_id, text_key, tree`` of unedited texts (``text_key`` as in ``text_key()``), ``edits`` holds ``doc_id, start, end, new``.
    """
    path = tokenizer or default_tokenizer()
    kind = trees.select("doc_id").dtypes[0][1]
    lists = edits.filter("doc_id IS NOT NULL").groupBy("doc_id").agg(F.sort_array(F.collect_list(F.struct("start", "end", "new"))).alias("edits"))
    rows = docs.select(F.col(doc_id).alias("doc_id"), text_key(text).alias("text_key"), F.col(text).alias("text"))
    rows = rows.join(lists, "doc_id").join(trees.dropDuplicates(["doc_id", "text_key"]), ["doc_id", "text_key"]).dropDuplicates(["doc_id", "text_key"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(path)
        for batch in batches:
            for part, texts in text_slices(batch, 2):
                done: list = []
                for t, todo, tree in zip(texts, part.column(3).to_pylist(), part.column(4).to_pylist(), strict=True):
                    doc = TokenTree(enc, t.decode("utf-8", "replace") if t else "", list(zip(tree["chars"], tree["tokens"], strict=True)))
                    shift = edge = 0
                    for e in todo:
                        if e["start"] < edge or e["end"] < e["start"]:
                            raise ValueError("edits of a document overlap")
                        edge = e["end"]
                        doc.edit(e["start"] + shift, e["end"] + shift, e["new"])
                        shift += len(e["new"]) - (e["end"] - e["start"])
                    done.append((doc.text.encode(), {"chars": [a for a, _ in doc.sums], "tokens": [b for _, b in doc.sums]}, len(todo), doc.encoded))
                texts, sums, n, encoded = zip(*done, strict=True)
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(texts, pa.binary()).cast(pa.string()), pa.array(sums, part.column(4).type), pa.array(n, pa.int64()), pa.array(encoded, pa.int64())], names=["doc_id", "text_key", "text", "tree", "n_edits", "n_reencoded"])

    columns = ["doc_id", "text_key", F.col("text").cast("binary").alias("text"), "edits", "tree"]
    return rows.select(columns).mapInArrow(run, f"doc_id {kind}, text_key long, text string, tree {_TREE}, n_edits long, n_reencoded long")


def text_key(text: str = "text"):
    return F.xxhash64(F.col(text))


#: Spans that the default edit list redacts: mail addresses, key assignments, long numbers and IPv4 addresses.
REDACT = regex.compile(r"[\w.+-]+@[\w-]+\.[\w.]+|token = \"[0-9a-f]+\"|\b\d{13,19}\b|\b\d{1,3}(?:\.\d{1,3}){3}\b")
PLACEHOLDER = "[removed]"


def redactions(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Edits ``doc_id, start, end, new`` that replace personal data and secrets; positions are characters of the text."""

    def setup():
        return lambda texts: [[{"start": m.start(), "end": m.end(), "new": PLACEHOLDER} for m in REDACT.finditer(t.decode("utf-8", "replace"))] if t else [] for t in texts]

    name = free_name(docs, "edits")
    found = docs.select(F.col(doc_id).alias("doc_id"), text_column(setup, "array<struct<start:bigint,end:bigint,new:string>>", text).alias(name))
    return found.select("doc_id", F.explode(name).alias("e")).select("doc_id", "e.start", "e.end", "e.new")


def edited_counts(docs: DataFrame, edits: DataFrame | None = None, *, doc_id: str = "doc_id", text: str = "text", tokenizer: str | None = None) -> DataFrame:
    """Per row of ``docs``: ``doc_id, n_tokens, n_edits, n_tokens_edited, n_reencoded`` (pre-tokens encoded for the edits)."""
    rows = docs.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text"))
    trees = token_trees(rows.withColumn("text_key", text_key()), tokenizer=tokenizer).select("doc_id", "text_key", "tree")
    trees = Scratch(docs.sparkSession, "tokens").save(trees, "trees")
    done = apply_edits(trees, redactions(rows) if edits is None else edits, rows, tokenizer=tokenizer)
    done = done.select("doc_id", "text_key", "n_edits", F.col("tree.tokens")[1].cast("long").alias("edited"), "n_reencoded")
    before = trees.select("doc_id", "text_key", F.col("tree.tokens")[1].cast("long").alias("n_tokens"))
    none = lambda c: F.coalesce(c, F.lit(0).cast("long")).alias(c)
    return before.join(done, ["doc_id", "text_key"], "left").select("doc_id", "n_tokens", none("n_edits"), F.coalesce("edited", "n_tokens").alias("n_tokens_edited"), none("n_reencoded"))


def op7_token_counts(spark, sf_dir: str) -> DataFrame:
    """Token counts of whole ``documents`` before and after redacting edits."""
    return edited_counts(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
