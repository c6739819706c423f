"""The pipeline's stages, each on its predecessor's rows, and the chain against brute force."""

import random
import re
from collections import Counter

import numpy as np

import corpus_pipeline
from setsim.llm import quality, tokens


def test_stages(spark, sf, tmp_path):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, docs, sf)
        if k < len(corpus_pipeline.STAGES) - 1:
            assert out.columns == docs.columns, name
        out.write.parquet(str(tmp_path / name))
        after = spark.read.parquet(str(tmp_path / name))
        assert 0 < after.count() and (k == len(corpus_pipeline.STAGES) - 1 or after.count() <= docs.count())
        docs = after
    assert corpus_pipeline.run(spark, sf).count() == docs.count()


def _line_sets(t):
    return [frozenset(re.split("[ \t\x0b\f\r]+", x.lower())) - {""} for x in t.split("\n")]


def _shingles(t):
    w = re.findall(r"[^\x20\x09-\x0D]+", t.lower())
    return set(zip(*[w[i:] for i in range(5)], strict=False)) if len(w) >= 5 else ({tuple(w)} if w else set())


def _near(a, b, num, den):
    return len(a & b) * den >= len(a | b) * num and bool(a) and bool(b)


def test_chain_equals_brute_force(spark, tmp_path):
    rng = random.Random(21)
    vocab = ["".join(rng.choice("abcdefghijklmnop") for _ in range(rng.randint(3, 9))) for _ in range(600)]
    prose = lambda n: " ".join(rng.choice(vocab) for _ in range(n))
    texts = ["\n".join(prose(rng.randint(4, 25)) for _ in range(rng.randint(1, 6))) for _ in range(60)]
    texts += [texts[3], texts[4] + " more", texts[5].replace("\n", "\n\n"), prose(20) + "\n" + texts[6].split("\n")[0], "", None]
    leak = prose(14)
    texts += [prose(8) + " " + leak + " " + prose(9)]
    texts += [" ".join("#$%&!!" for _ in range(40)) for _ in range(15)]
    d = str(tmp_path / "sf")
    rows = [(i, t, "xx", "web", len(t or "")) for i, t in enumerate(texts)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{d}/documents.parquet")
    labels = [(i, int("#" not in (t or "")), 0) for i, t in enumerate(texts)]
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{d}/labels.parquet")
    spark.createDataFrame([(7, leak)], "item_id long, text string").write.parquet(f"{d}/benchmark.parquet")
    got = corpus_pipeline.run(spark, d).collect()

    # quality: the same model on features worked out here, row by row
    source = spark.read.parquet(f"{d}/documents.parquet")
    model = quality.train(source, spark.read.parquet(f"{d}/labels.parquet"))
    kept = {i: t for i, t in enumerate(texts) if model.score(np.array([quality.features_of(t.encode() if t else None)]))[0] >= 0.3}
    assert len(kept) < len(texts) and not any("#" in (t or "") for t in kept.values())
    # lines, in order of ids: a line goes if any earlier one is near
    seen, after = [], {}
    for i in sorted(kept):
        if kept[i] is None:
            after[i] = None
            continue
        stay = []
        for line, s in zip(kept[i].split("\n"), _line_sets(kept[i]), strict=True):
            if not s or not any(_near(s, o, 4, 5) for o in seen):
                stay.append(line)
            seen += [s] if s else []
        if stay:
            after[i] = "\n".join(stay)
    # one of each group, the least id
    sets = {i: _shingles(t) if t else set() for i, t in after.items()}
    name = {i: i for i in after}
    for _ in after:
        for i in after:
            for j in after:
                if _near(sets[i], sets[j], 80, 100):
                    name[i] = name[j] = min(name[i], name[j])
    after = {i: t for i, t in after.items() if name[i] == i}
    # no window of the benchmark
    words = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (t or "").lower())
    windows = {tuple(words(leak)[k : k + 10]) for k in range(5)}
    after = {i: t for i, t in after.items() if not any(tuple(words(t)[k : k + 10]) in windows for k in range(len(words(t))))}
    # packing: every id once, sequences without gaps
    enc = tokens.encoder(tokens.default_tokenizer()).tokenizer
    want = {i: len(enc.encode(t or "", add_special_tokens=False).ids) + 1 for i, t in after.items()}
    assert Counter(r.doc_id for r in got if r.start == 0) == Counter(list(want)) and {r.doc_id: r.doc_tokens for r in got} == want
    total = Counter()
    ends = {}
    for r in got:
        total[r.doc_id] += r.length
        ends.setdefault(r.sequence_id, []).append((r.offset, r.length))
    assert dict(total) == want
    assert all(a == sum(n for _, n in sorted(v)[:k]) for v in ends.values() for k, (a, _) in enumerate(sorted(v)))
