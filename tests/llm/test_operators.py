"""Every operator on small tables with nulls, empty and long texts, ties, repeated rows, clashing columns and no rows."""

import hashlib
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from setsim.llm import decontaminate as deco
from setsim.llm import embeddings, html, language, lines, near_duplicates, packing, quality, sharding, tokens

RNG = random.Random(11)
VOCAB = ["".join(RNG.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(RNG.randint(2, 8))) for _ in range(400)]


def prose(n, rng=RNG):
    return " ".join(rng.choice(VOCAB) for _ in range(n))


def corpus():
    rng = random.Random(5)
    texts = [prose(rng.randint(1, 120), rng) for _ in range(60)]
    texts += [texts[3], texts[3], texts[7] + " extra", texts[8].upper(), prose(9000, rng), "", None, "   \n ", "one two", "one two", "été naïve 中文 <|endoftext|> x"]
    texts += ["\n".join([texts[1], texts[2], "", texts[1] + " z"]), "a\r\nb\tc\x0bd", "mail x.y@z.org or 10.0.0.1, καλημέρα 1234567890123456 κόσμε"]
    rows = [(i, t) for i, t in enumerate(texts)]
    return rows + [(5, texts[5]), (None, texts[6])]


SCHEMA = "doc_id long, text string"


@pytest.fixture(scope="module")
def docs(spark, tmp_path_factory):
    path = str(tmp_path_factory.mktemp("docs") / "t")
    df = spark.createDataFrame(corpus(), SCHEMA)
    clash = {c: F.lit(c) for c in ("score", "shard", "slot", "size", "n", "d", "h", "t", "hits", "__kept", "word", "cid", "sig", "n_chars", "__h", "__t", "__size", "__class", "__shard", "__slice", "__quality", "__row")}
    df.withColumns(clash).write.parquet(path)
    return spark.read.parquet(path)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def test_sharding(docs, empty):
    got = sharding.shard_by_bytes(docs, 4).select("doc_id", "text", "size", "shard", "slot").collect()
    assert Counter((r.doc_id, r.text) for r in got) == Counter(corpus())
    assert all(r["size"] == len((r.text or "").encode()) + 8 for r in got)
    slots = defaultdict(list)
    for r in got:
        slots[r.shard].append(r.slot)
    assert all(sorted(v) == list(range(len(v))) for v in slots.values())
    assert sharding.shard_by_bytes(empty, 4).count() == 0


def test_sharding_splits_one_text(spark):
    df = spark.range(600).select(F.col("id").alias("doc_id"), F.when(F.col("id") < 400, "same text").otherwise(F.concat(F.lit("text "), "id")).alias("text"))
    sums = [r[1] for r in sharding.shard_by_bytes(df, 6).groupBy("shard").agg(F.sum("size")).collect()]
    assert len(sums) == 6 and max(sums) - min(sums) <= 64


def _words(t):
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))


@pytest.mark.parametrize("block_bytes", [1 << 24, 300])
def test_decontamination(spark, docs, empty, block_bytes):
    texts = [t for _, t in corpus() if t]
    long = next(t for t in texts if len(t) > 40_000).split()
    items = [(1, " ".join(long[100:130])), (2, " ".join(long[115:140]).upper()), (3, "one two"), (10, prose(20)), (11, ""), (12, None), (None, " ".join(long[500:512])), (1, " ".join(long[100:130]))]
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = deco.benchmark_hits(docs, bench, out="found", block_bytes=block_bytes).select("doc_id", "text", "found").collect()
    assert len(got) == len(corpus())
    for r in got:
        w = _words(r.text)
        hit, names = set(), set()
        for i, t in items:
            v = _words(t)
            for a in range(max(1, len(v) - 9) if v else 0):
                win = v[a : a + 10]
                for p in range(len(w) - len(win) + 1):
                    if w[p : p + len(win)] == win:
                        hit |= set(range(p, p + len(win)))
                        names |= {str(i)} if i is not None else set()
        assert r.found.n_words == len(w)
        assert {p for a, b in zip(r.found.starts, r.found.ends, strict=True) for p in range(a, b)} == hit
        assert r.found["items"] == sorted(names)
    assert deco.decontaminate(docs, bench).columns == docs.columns
    assert deco.benchmark_hits(empty, bench).count() == 0
    assert deco.benchmark_hits(docs, bench.limit(0)).filter("size(hits.starts) > 0").isEmpty()


def _shingles(t):
    w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
    return set(zip(*[w[i:] for i in range(5)], strict=False)) if len(w) >= 5 else ({tuple(w)} if w else set())


def _grouped(rows, linked):
    parent = {}

    def find(x):
        parent.setdefault(x, x)
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in linked:
        a, b = find(a), find(b)
        parent[max(a, b)] = min(a, b)
    return {x: find(x) for x in rows}


def test_near_duplicates(spark, docs, empty, tmp_path):
    rng = random.Random(8)
    base = [prose(n, rng).split() for n in (6, 12, 30, 60, 200, 800) for _ in range(4)]
    rows = [(i, t) for i, t in corpus()]
    for k, w in enumerate(base):
        for j in range(6):
            v = list(w)
            for _ in range(rng.randint(0, max(1, len(v) // 40))):
                v[rng.randrange(len(v))] = rng.choice(VOCAB)
            rows.append((1000 + 10 * k + j, " ".join(v)))
    path = str(tmp_path / "t")
    spark.createDataFrame(rows, SCHEMA).write.parquet(path)
    got = near_duplicates.near_duplicates(spark.read.parquet(path)).collect()
    sets = [(i, _shingles(t)) for i, t in rows]
    links = [(a, b) for x, (a, s) in enumerate(sets) for b, t in sets[:x] if a is not None and b is not None and s and t and 100 * len(s & t) >= 80 * len(s | t)]
    want = _grouped([i for i, _ in rows if i is not None], links)
    assert Counter((r.doc_id, r.n_shingles) for r in got) == Counter((i, len(s)) for i, s in sets)
    assert {r.doc_id: r.component_id for r in got if r.doc_id is not None} == want
    kept = near_duplicates.keep_one(docs)
    assert kept.columns == docs.columns and kept.filter("doc_id IS NOT NULL").groupBy("doc_id").count().filter("count > 1").isEmpty()
    assert near_duplicates.near_duplicates(empty).count() == 0


@pytest.mark.parametrize("n", range(7))
def test_shingles_of_a_lone_short_text(n):
    text = " ".join(VOCAB[:n]).encode()
    alone, beside = near_duplicates.shingle_sets([text])[0], near_duplicates.shingle_sets([prose(50).encode(), text, None])[1]
    assert len(alone) == min(n, max(1, n - 4)) and alone.tolist() == beside.tolist()


def test_signatures_meet():
    rng = np.random.default_rng(2)
    for _ in range(400):
        n = int(rng.integers(4, 300))
        a = np.unique(rng.integers(0, 2**63, n, dtype=np.uint64))
        cut = int(rng.integers(0, max(1, len(a) // 9) + 1))
        b = np.unique(np.concatenate([a[cut:], rng.integers(0, 2**63, int(rng.integers(0, max(1, len(a) // 9) + 1)), dtype=np.uint64)]))
        same = len(np.intersect1d(a, b))
        hot = np.sort(rng.choice(a, int(rng.integers(0, len(a))), replace=False)) if rng.random() < 0.5 else None
        if same and 5 * same >= 4 * (len(a) + len(b) - same) and same < max(len(a), len(b)):
            assert len(np.intersect1d(near_duplicates.signatures(a, hot), near_duplicates.signatures(b, hot)))


def test_embeddings(spark):
    rng = np.random.default_rng(3)
    x = rng.standard_normal((60, 16))
    x = np.concatenate([x, x[:20] + 0.08 * rng.standard_normal((20, 16)), x[:5], 3 * x[5:8], np.repeat(x[9:10], 40, 0) + 0.02 * rng.standard_normal((40, 16))]).astype(np.float32)
    rows = [(i, v.tolist()) for i, v in enumerate(x)]
    odd = [(900, None), (901, []), (902, [0.0] * 16), (903, [float("nan")] * 16), (904, [None] * 16), (905, [1.0] * 3), (None, x[0].tolist())]
    got = {r.vec_id: r for r in embeddings.link_embeddings(spark.createDataFrame(rows + odd, "vec_id long, embedding array<float>")).collect()}
    y = x.astype(float)
    y /= np.linalg.norm(y, axis=1, keepdims=True)
    close = y @ y.T >= 0.95
    np.fill_diagonal(close, False)
    want = _grouped(range(len(x)), [(int(a), int(b)) for a, b in np.argwhere(close)])
    assert {i: got[i].component_id for i in range(len(x))} == want
    extra = close[0].copy()
    extra[0] = True  # the vector with a null id is a copy of vector 0
    assert [got[i].n_links for i in range(len(x))] == [int(close[i].sum()) + int(extra[i]) for i in range(len(x))]
    assert all(got[i].n_links == 0 and got[i].component_id == i and got[i].kept for i in range(900, 906))
    assert not got[None].kept and got[None].component_id is None
    assert embeddings.link_embeddings(spark.createDataFrame([], "vec_id long, embedding array<float>")).count() == 0


def test_embedding_blocks(spark, monkeypatch):
    monkeypatch.setattr(embeddings, "BLOCK", 7)
    rng = np.random.default_rng(4)
    x = (rng.standard_normal((1, 8)) + 0.1 * rng.standard_normal((50, 8))).astype(np.float32)
    got = embeddings.link_embeddings(spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>")).collect()
    y = x.astype(float) / np.linalg.norm(x.astype(float), axis=1, keepdims=True)
    want = (y @ y.T >= 0.95).sum(1) - 1
    assert [r.n_links for r in sorted(got, key=lambda r: r.vec_id)] == want.tolist()


def test_quality(spark, docs, empty):
    rng = random.Random(1)
    rows = [(i, prose(40, rng) if i % 3 else " ".join(w.upper() + "!!" for w in prose(40, rng).split())) for i in range(600)]
    labels = [(i, int(i % 3 > 0), 0) for i, _ in rows] + [(1, None, 0), (None, 1, 0)]
    df, lab = spark.createDataFrame(rows, SCHEMA), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")
    model = quality.train(df, lab)
    got = quality.quality_scores(df, model).collect()
    test = [r for r in got if zlib.crc32(str(r.doc_id).encode()) % 5 == 0]
    assert np.mean([(r.score >= 0.3) == (r.doc_id % 3 > 0) for r in test]) > 0.97
    assert all(0 <= r.score <= 1 for r in quality.quality_scores(docs, model).collect())
    assert quality.keep_good(docs, lab).columns == docs.columns
    assert {r.score for r in quality.quality_scores(docs, quality.train(docs, lab.limit(0))).collect()} == {0.5}
    assert quality.quality_scores(empty, model).count() == 0


def test_pairs_of_features_are_learnt():
    rng = np.random.default_rng(0)
    x = rng.random((4000, len(quality.FEATURES)))
    y = ((x[:, 0] > 0.5) ^ (x[:, 1] > 0.5)).astype(float)
    assert np.mean((quality.fit(x, y).score(x) > 0.5) == y) > 0.95


def test_language(spark, docs, empty):
    rng = random.Random(2)
    alphabets = {"aa": "abcde", "bb": "abxyz", "cc": "mnopq"}
    rows = [(i, " ".join("".join(rng.choice(alphabets[g]) for _ in range(6)) for _ in range(30)), g) for i in range(240) for g in [list(alphabets)[i % 3]]]
    rows += [(900, None, "aa"), (901, "", None), (902, "12 !", "bb"), (903, "mnopq nopqm", None)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    texts = language.training_texts(df)
    got = {r.doc_id: r.g for r in df.select("doc_id", language.language_column(spark, texts).alias("g")).collect()}
    assert np.mean([got[i].lang == g for i, _, g in rows[:240]]) > 0.98
    assert [got[i].lang for i in (900, 901, 902, 903)] == ["und", "und", "und", "cc"] and all(0 <= g.score <= 1 for g in got.values())
    assert docs.select(language.language_column(spark, {}).alias("g")).filter("g.lang <> 'und'").isEmpty()
    assert language.training_texts(empty.withColumn("lang", F.lit(None).cast("string"))) == {}


def test_cross_parsing_phrases():
    train, text = b"abracadabra", b"abracabrax dabra zz"
    p = language.CrossParser({"x": train})
    fold = train.decode()
    count, at = 0, 0
    while at < len(text):
        n = 0
        while at + n < len(text) and text[at : at + n + 1].decode() in fold:
            n += 1
        at += max(1, n)
        count += 1
    assert p.phrases([text])[0, 0] == count


def test_token_counts(spark, docs, empty):
    enc = tokens.encoder(tokens.default_tokenizer())
    count = lambda t: len(enc.tokenizer.encode(t or "", add_special_tokens=False).ids)
    want = Counter()
    for i, t in corpus():
        n = len(tokens.REDACT.findall(t or "")) if i is not None else 0
        want[i, count(t), n, count(tokens.REDACT.sub(tokens.PLACEHOLDER, t) if n else t)] += 1
    got = tokens.edited_counts(docs).collect()
    assert Counter((r.doc_id, r.n_tokens, r.n_edits, r.n_tokens_edited) for r in got) == want
    assert sum(r.n_edits for r in got) == 3
    assert tokens.edited_counts(empty).count() == 0
    rows = spark.createDataFrame([(1, "Γειά σου 汉字 x@y.de "), (1, "other 12 text"), (2, "abc"), (None, "abc")], SCHEMA)
    edits = spark.createDataFrame([(1, 5, 8, "κόσμε!"), (1, 0, 2, ""), (9, 0, 1, "x")], "doc_id long, start long, end long, new string")
    got = {(r.doc_id, r.n_edits, r.n_tokens_edited) for r in tokens.edited_counts(rows, edits).collect()}
    cut = lambda t: t[2:5] + "κόσμε!" + t[8:]
    assert got == {(1, 2, count(cut("Γειά σου 汉字 x@y.de "))), (1, 2, count(cut("other 12 text"))), (2, 0, count("abc")), (None, 0, count("abc"))}
    with pytest.raises(Exception, match="overlap"):
        tokens.edited_counts(rows, edits.union(edits)).collect()


def test_edits_equal_a_fresh_count():
    enc = tokens.encoder(tokens.default_tokenizer())
    rng = random.Random(6)
    parts = ["", "x", " ", "'l", "l", "e'", "\n\n", "  ", "foo bar 12", "é$", "<|endof", "text|>", "汉字", " שלום", "\u0558", "<|endoftext|>", "w " * 300]
    for k in range(80):
        text = prose(rng.randint(0, 300), rng)
        if k % 2:
            text = text.translate(str.maketrans("abcdef ", "αβ汉д3ж\u3000"))
        doc = tokens.TokenTree(enc, text)
        for _ in range(8):
            a = rng.randrange(len(text) + 1)
            b = min(len(text), a + rng.choice([0, 0, 1, 3, 200]))
            new = rng.choice(parts)
            doc.edit(a, b, new)
            text = text[:a] + new + text[b:]
            assert doc.text == text and doc.tokens() == len(enc.tokenizer.encode(text, add_special_tokens=False).ids)
            assert doc.sums[1][0] == len(text)
            doc = tokens.TokenTree(enc, text, list(doc.sums))  # as stored and read again


def test_edits_are_local():
    enc = tokens.encoder(tokens.default_tokenizer())
    for table in ({}, str.maketrans("abcdef", "αβγдεж")):
        text = prose(20_000).translate(table)
        doc = tokens.TokenTree(enc, text)
        doc.encoded, before = 0, list(doc.sums)
        doc.edit(60_000, 60_004, "new")
        assert 0 < doc.encoded < 40
        assert sum(x != y for x, y in zip(before, doc.sums, strict=True)) <= 2 * len(doc.sums).bit_length()


def test_pieces_are_the_tokenizers():
    enc = tokens.encoder(tokens.default_tokenizer())
    for low in (*range(0, 0x20000, 0x1000), 0x2B000, 0x2C000, 0x32000, 0x3D000, 0xE0000, 0x10F000):
        text = "".join(f"a{chr(c)}1{chr(c)} {chr(c)}{chr(c)}. " for c in range(low, low + 0x1000) if not 0xD800 <= c < 0xE000)
        want = enc.tokenizer.pre_tokenizer.pre_tokenize_str(text)
        assert list(enc.pieces(text)) == [text[a:b] for _, (a, b) in want]
        assert enc.ids(text) == np.array(enc.tokenizer.encode(text, add_special_tokens=False).ids, "<u4").tobytes()


def test_packing(spark, docs, empty):
    enc = tokens.encoder(tokens.default_tokenizer()).tokenizer
    got = packing.pack(docs).collect()
    by_seq, ids_of = defaultdict(list), defaultdict(list)
    for r in got:
        assert len(r.ids) == 4 * r.length <= 4096
        by_seq[r.sequence_id].append((r.offset, r.length))
        ids_of[(r.doc_id, r.doc_tokens)].append((r.start, bytes(r.ids)))
    for v in by_seq.values():
        at = 0
        for offset, n in sorted(v):
            assert offset == at
            at += n
        assert at <= 1024
    want = Counter((i, np.array([*enc.encode(t or "", add_special_tokens=False).ids, 0], "<u4").tobytes()) for i, t in corpus())
    whole = Counter()
    for (i, n), v in ids_of.items():
        copies = Counter(v)
        k = min(copies.values())
        if len({s for s, _ in copies}) == len(copies):
            whole[(i, b"".join(b for _, b in sorted(copies)))] += k
    assert whole == want
    assert packing.pack(empty).count() == 0
    total = sum(r.length for r in got)
    assert len(by_seq) <= total / 1024 * 1.1 + 2


def test_packing_of_short_texts(spark):
    rows = [(i, None if i % 5 == 0 else " ".join(VOCAB[i % 400 : i % 400 + i % 3])) for i in range(6000)]
    got = packing.pack(spark.createDataFrame(rows, SCHEMA).repartition(3)).collect()
    by_seq = defaultdict(list)
    for r in got:
        by_seq[r.sequence_id].append((r.offset, r.length))
    for v in by_seq.values():
        v.sort()
        assert [a for a, _ in v] == [sum(n for _, n in v[:k]) for k in range(len(v))] and sum(n for _, n in v) <= 1024
    assert {r.doc_id for r in got} == set(range(6000)) and sum(r.length for r in got) == sum({r.doc_id: r.doc_tokens for r in got}.values())
    assert len(by_seq) <= sum(r.length for r in got) / 1024 * 1.02 + 1


def test_cuts():
    for n in range(1, 3000):
        pieces = packing.cuts(n)
        assert sum(p[1] for p in pieces) == n and all(p[1] <= 1024 // p[2] for p in pieces) and len(pieces) <= n // 1024 + 6


def test_lines(spark, docs, empty, tmp_path):
    rng = random.Random(3)
    base = [prose(rng.randint(1, 60), rng) for _ in range(30)]
    rows = list(corpus())
    for i in range(60):
        picked = []
        for _ in range(rng.randint(1, 8)):
            w = rng.choice(base).split()
            for _ in range(rng.choice([0, 0, 1, 2, 9])):
                w[rng.randrange(len(w))] = rng.choice(VOCAB)
            picked.append(" ".join(w) + rng.choice(["", "", " ", "\r"]))
        rows.append((2000 + i, "\n".join([*picked, "", " "])))
    rows = [r for r in rows if r[0] is not None]
    spark.createDataFrame(rows, SCHEMA).write.parquet(str(tmp_path / "t"))
    got = {r.doc_id: r for r in lines.dedup_lines(spark.read.parquet(str(tmp_path / "t")), counts=True).collect()}
    inv, sets, done = defaultdict(list), [], set()
    for i, t in sorted(rows, key=lambda r: r[0]):
        if i in done:
            continue
        done.add(i)
        if t is None:
            assert got[i].text is None
            continue
        kept = []
        for line in t.split("\n"):
            s = set(re.split("[ \t\x0b\f\r]+", line.lower())) - {""}
            c = Counter()
            for g in s:
                c.update(inv[g])
            if not any(9 * o >= 4 * (len(s) + len(sets[j])) for j, o in c.items()):
                kept.append(line)
            if s:
                for g in s:
                    inv[g].append(len(sets))
                sets.append(s)
        assert got[i].text == "\n".join(kept), i
        assert got[i].n_removed == len(t.split("\n")) - len(kept)
    out = lines.dedup_lines(docs, drop_emptied=True)
    assert out.columns == docs.columns and out.count() <= docs.count()
    assert lines.dedup_lines(empty).count() == 0


def test_line_sets_are_aggregated_for_repeated_rows_only(spark, monkeypatch):
    """Word sets to verify are neither sorted nor shuffled by class where no row is repeated; results are the same."""
    rows = [(k, f"a{k % 3} b c d e f g h i j\n \t\n\x0b x{k}  y") for k in range(12)]
    plans, save = {}, lines.Scratch.save

    def seen(self, df, name, **more):
        plans[name] = df._jdf.queryExecution().executedPlan().toString()
        return save(self, df, name, **more)

    monkeypatch.setattr(lines.Scratch, "save", seen)
    want = {k: "\n".join([text.split("\n")[0]] * (k == 0) + [" \t", text.split("\n")[2]]) for k, text in rows}
    for given, times in ((rows, 1), (rows + rows[:5], 2)):
        out = lines.dedup_lines(spark.createDataFrame(given, "doc_id long, text string")).collect()
        assert sorted((r.doc_id, r.text) for r in out) == sorted((k, want[k]) for k, _ in given)
        assert ("SortAggregate" in plans["first_sets"]) == (times > 1)
        assert "RLIKE" not in plans["classes"]


def test_line_plan_is_native(docs):
    plan = lines.dedup_lines(docs)._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Pandas|Arrow", plan)


@pytest.mark.parametrize(
    "page,want",
    [
        (None, ""),
        ("", ""),
        ("<html><body><nav><a>menu</a></nav><article><h1>Title &amp; more</h1><p><b>One  two.<br><p>Three\n four.</p><aside>no</aside><div class='comments'><p>reader</p></div></article><footer>f</footer>", "Title & more\nOne two.\nThree four."),
        ("<body><header><h1>Site</h1></header><div class=ad>Buy</div><div id='content'><p>A long paragraph, with commas, and words.</p><p>Another long paragraph, with more words.</p></div><form>x</form><script>var a='<p>no</p>'</script></body>", "A long paragraph, with commas, and words.\nAnother long paragraph, with more words."),
        ("<article><p>open <!-- never closed", "open"),
        ("<main><ul><li>one<li>two</ul>tail</main></div></p>", "one\ntwo\ntail"),
    ],
)
def test_html(page, want):
    assert (html.extract(page) if page else "") == want


_PROSE = [f"Sentence {k}, with a few more words, goes on, and on, and on; it ends here. " * 4 for k in range(8)]
_LONG = "".join(f"<p>{t}</p>" for t in _PROSE)
_TEXT = [t.strip() for t in _PROSE]
_ITEMS = ["flour", "two eggs", "salt", "milk", "sugar", "oil"]
_LIST = "<ul>" + "".join(f"<li>{t}</li>" for t in _ITEMS) + "</ul>"
_LINKS = "<ul>" + "".join(f"<li><a href='/{k}'>Go there {k}</a></li>" for k in range(6)) + "</ul>"


@pytest.mark.parametrize(
    "page,want",
    [
        (f"<body><div><h1>A title of a page</h1>{_LONG}</div></body>", ["A title of a page", *_TEXT]),
        (f"<body><h1>A title of a page</h1><p>By us</p><div>{_LONG}</div><div>All rights</div></body>", ["A title of a page", "By us", *_TEXT]),
        (f"<body>{_LINKS}<div><h1>Cake, at last</h1>{_LONG}{_LIST}<h2>End</h2>{_LONG}{_LIST}</div></body>", ["Cake, at last", *_TEXT, *_ITEMS, "End", *_TEXT, *_ITEMS]),
        (f"<body><div><h2>One</h2>{_LIST}{_LONG}</div><div>{_LINKS}</div></body>", ["One", *_ITEMS, *_TEXT]),
    ],
)
def test_html_without_article_keeps_its_region(page, want):
    assert html.extract(page).split("\n") == want


@pytest.mark.parametrize(
    "page,want",
    [
        (f"<body><article><h1>T</h1>{_LONG}{_LIST}<div>{_LINKS}</div></article></body>", ["T", *_TEXT, *_ITEMS]),
        (f"<body><div>{_LONG}</div><article><b>Teaser one</b></article><article><b>Teaser two</b></article></body>", _TEXT),
        (f"<body><div>{_LONG}</div><article><b>A note</b></article></body>", [*_TEXT, "A note"]),
        (f"<body><main><h1>T</h1>{_LONG}<p>See <a href='/x'>this</a></p></main><div><p>All rights</p></div></body>", ["T", *_TEXT, "See this"]),
    ],
)
def test_html_ratios_run_on_declared_pages(page, want):
    assert html.extract(page).split("\n") == want


def test_html_table(spark):
    df = spark.createDataFrame([(1, "u", None), (2, "u", "<article>x &lt; y</article>"), (2, "u", "<article>x &lt; y</article>")], "page_id long, url string, html string")
    assert sorted(r.text for r in html.main_text(df).collect()) == ["", "x < y", "x < y"]
    assert html.main_text(df.limit(0)).count() == 0


def test_digests(spark, sf):
    from setsim.llm.queries import QUERIES

    want = {
        "op1_sharding": ["doc_id", "size", "text_crc32", "law", "shard", "slot", "grown_shard"], "op2_decontaminate": ["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated"],
        "op3_near_duplicates": ["doc_id", "n_shingles", "component_id"], "op4_embeddings": ["vec_id", "n_links", "component_id", "kept"], "op5_quality": ["doc_id", "held_out", "score", "predicted"],
        "op6_language": ["doc_id", "held_out", "lang_pred", "score"], "op8_packing": ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"], "op10_html": ["page_id", "url", "text", "n_chars"],
    }
    for name, columns in want.items():
        assert QUERIES[name](spark, sf).columns == columns, name
    assert hashlib.sha256(b"").hexdigest() in {r.items_sha256 for r in QUERIES["op2_decontaminate"](spark, sf).collect()}


def test_html_without_declared_region(sf):
    """With article and main renamed to div, tag-path ratios alone find the same text."""
    import pyarrow.parquet as pq

    pages = [p for p in pq.read_table(f"{sf}/pages.parquet")["html"].to_pylist() if p]
    same = sum(html.extract(p) == html.extract(re.sub(r"<(/?)(article|main)\b", r"<\1div", p, flags=re.I)) for p in pages)
    assert pages and same >= 0.98 * len(pages)


def test_tag_path_ratios():
    """Sums per path, smoothing, fusion and threshold against plain loops."""
    rng = random.Random(12)
    for _ in range(40):
        blocks = [html.Block(rng.choice(["a, b. ", "word "]) * rng.randint(1, 30), rng.choice(["div/p", "div/ul/li", "div", "td"]), False, 0, (), False) for _ in range(rng.randint(1, 25))]
        per = defaultdict(list)
        for b in blocks:
            per[b.path].append((len(b.text), sum(c in ".,;:!?" for c in b.text)))
        series = [[sum(x[k] for x in per[b.path]) / len(per[b.path]) for b in blocks] for k in (0, 1)]
        near = lambda v, i: sum(w * v[min(len(v) - 1, max(0, i + d))] for d, w in zip((-2, -1, 0, 1, 2), (0.06, 0.24, 0.4, 0.24, 0.06), strict=True))
        fused = [near(series[0], i) * (near(series[1], i) + 0.1) for i in range(len(blocks))]
        best = {p: max(f for f, b in zip(fused, blocks, strict=True) if b.path == p) for p in per}
        limit = 0.5 * sum(fused) / len(fused)
        got = html._content(blocks, 0.5)
        assert all(g == (best[b.path] >= limit) for g, b in zip(got, blocks, strict=True) if abs(best[b.path] - limit) > 1e-9)


def test_html_long_and_odd_pages(spark):
    long = "<body><nav>" + "<a href='/x'>menu</a>" * 2000 + "</nav><div>" + _LONG * 300 + "</div></body>"
    rows = [(1, "u", long), (1, "u", long), (2, "u", None), (3, "u", "<p>" * 3000 + "deep"), (4, "u", "no tags, only text"), (None, None, "<article><p>x, y.</p></article>")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumns({"text": F.lit("old"), "out": F.lit(1)})
    got = [(r.page_id, r.text, r.out) for r in html.main_text(pages).collect()]
    want = "\n".join(_TEXT * 300)
    assert sorted(got, key=str) == sorted([(1, want, 1), (1, want, 1), (2, "", 1), (3, "deep", 1), (4, "no tags, only text", 1), (None, "x, y.", 1)], key=str)
    assert html.main_text(pages.limit(0)).count() == 0


def test_tree_step():
    """The first cut of a boosting tree is the best of all cuts."""
    rng = np.random.default_rng(5)
    for _ in range(50):
        n = int(rng.integers(2, 20))
        g, h = rng.normal(size=n), rng.random(n) + 0.01
        gain = lambda a, b: (g[a:b].sum()) ** 2 / (h[a:b].sum() + 1)
        cut = max(range(1, n), key=lambda c: gain(0, c) + gain(c, n))
        step = quality._tree(g, h, 2)
        if gain(0, cut) + gain(cut, n) - gain(0, n) > 1e-6:
            assert np.allclose(step[:cut], g[:cut].sum() / (h[:cut].sum() + 1)) and np.allclose(step[cut:], g[cut:].sum() / (h[cut:].sum() + 1))


def test_working_names_survive(docs):
    """Columns that are called like the operators' own keep their values."""
    for out in (sharding.shard_by_bytes(docs, 4), lines.dedup_lines(docs), tokens.token_trees(docs)):
        for c in ("__h", "__t", "__size", "__quality", "__row", "__kept", "cid"):
            assert out.filter(F.col(f"`{c}`") != c).isEmpty(), c


def test_embeddings_at_the_threshold(spark):
    """Cosine 0.96 as 24 of 25 against 0.28 as 7 of 25: exact numbers on both sides of 0.95, and exactly at a threshold of 0.8."""
    rows = [(1, [1.0, 0.0]), (2, [24.0, 7.0]), (3, [7.0, 24.0]), (4, [-1.0, 0.0]), (5, [3.0, 4.0]), (6, [4.0, 3.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").withColumns({c: F.lit(c) for c in ("e", "rep", "n", "cid", "codes", "links", "component", "d", "t", "c")})
    got = {r.vec_id: (r.n_links, r.component_id, r.kept) for r in embeddings.link_embeddings(df).collect()}
    unit = lambda v: np.array(v) / np.linalg.norm(v)
    want = {i: sum(float(unit(x) @ unit(y)) >= 0.95 for j, y in rows if j != i) for i, x in rows}
    assert {i: g[0] for i, g in got.items()} == want and want[1] == 1 and got[4] == (0, 4, True)
