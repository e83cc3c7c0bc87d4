"""The corpus pipeline against a plain version of each filtering stage."""

import random
import re

import numpy as np

import corpus_pipeline


def test_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "near_duplicates", "decontamination", "mixing", "token_output"]
    clean = corpus_pipeline.stage_toxicity(spark, docs, sf)
    assert clean.columns == docs.columns
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    single = corpus_pipeline.stage_near_duplicates(spark, docs, sf)
    assert {r["doc_id"] for r in single.collect()} == plain_survivors(texts) and single.columns == docs.columns
    kept = corpus_pipeline.stage_decontamination(spark, docs, sf)
    items = [r["text"] for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    assert {r["doc_id"] for r in kept.collect()} == plain_clean(texts, items) and kept.columns == docs.columns
    mixed = corpus_pipeline.stage_mixing(spark, docs, sf)
    assert mixed.columns == docs.columns and mixed.select("doc_id").distinct().count() == docs.count()
    out = corpus_pipeline.stage_token_output(spark, mixed, sf)
    assert out.count() == mixed.count()


def test_run(spark, sf):
    out = corpus_pipeline.run(spark, sf).orderBy("start").collect()
    at = 0
    for r in out:
        assert r["start"] == at
        at += r["n_tokens"]
    assert out and corpus_pipeline.ORACLE_SQL is None
    assert not re.search("except ImportError", open(corpus_pipeline.__file__).read())


def plain_survivors(texts):
    """Smallest id of each component over five-word Jaccard of 0.8 or more, all pairs compared."""
    def shingles(text):
        words = (text or "").encode().lower().split()
        return {b" ".join(words[i : i + 5]) for i in range(max(1, len(words) - 4))} if words else set()

    sets, root = {i: shingles(t) for i, t in sorted(texts.items())}, {i: i for i in texts}
    def find(i):
        while root[i] != i:
            i = root[i]
        return i
    ids = list(sets)
    for n, a in enumerate(ids):
        for b in ids[n + 1 :]:
            if 10 * len(sets[a] & sets[b]) >= 8 * len(sets[a] | sets[b]):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    return {find(i) for i in ids}


def plain_clean(texts, items):
    """Documents of which less than a twentieth of the words lies in windows of 13 words that an item has too."""
    def words(text):
        return re.findall(rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (text or "").encode().lower())

    windows = {}
    for item in map(words, items):
        n = min(13, len(item))
        for i in range(len(item) - n + 1 if n else 0):
            windows.setdefault(n, set()).add(tuple(item[i : i + n]))
    clean = set()
    for i, text in texts.items():
        own, hit = words(text), set()
        for n, known in windows.items():
            for at in range(len(own) - n + 1):
                if tuple(own[at : at + n]) in known:
                    hit |= set(range(at, at + n))
        if not hit or 20 * len(hit) < len(own):
            clean.add(i)
    return clean


def test_stages_on_awkward_and_empty_tables(spark, sf):
    rows = [(None, "one two three four five six", "en", "s", 1), (None, "seven eight nine ten eleven twelve", None, None, None), (7, "alpha beta gamma", "en", "s", 2),
            (7, "delta epsilon zeta", "de", "s", 3), (8, None, None, None, None), (9, "", "fr", "s", 0), (10, "   ", "fr", "s", 3), (11, "same words here", "es", "s", 4),
            (11, "same words here", "es", "s", 4), (12, "wort " * 100_000, "de", "s", 5)]
    awkward = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint")
    for docs in (awkward, awkward.filter("doc_id > 99")):
        n = docs.count()
        for name, stage in corpus_pipeline.STAGES[:-1]:
            out = stage(spark, docs, sf)
            assert out.columns == docs.columns and out.schema.simpleString() == docs.schema.simpleString()
            got = out.count()
            assert got >= n if name == "mixing" else got <= n
            if name == "near_duplicates" and n:  # 8, 9 and 10 have no words; 11 is one row twice
                kept = sorted((r["doc_id"] or 0, r["text"]) for r in out.collect())
                assert [k for k, _ in kept] == [0, 0, 7, 7, 8, 11, 12]
        assert corpus_pipeline.stage_token_output(spark, docs, sf).count() == n


def test_near_copies_against_all_pairs(spark, sf):
    draw = random.Random(4)
    texts = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    at = max(texts) + 1
    for _ in range(60):
        words = [f"w{draw.randrange(10**6)}" for _ in range(draw.randrange(30, 300))]
        for cut in (0, 0.01, 0.02, 0.03, 0.04):
            texts[at] = " ".join(f"x{draw.randrange(10**6)}" if draw.random() < cut else w for w in words)
            at += 1
    texts |= {at: "a b c", at + 1: "A  B c", at + 2: "", at + 3: None, at + 4: "a b d"}
    docs = spark.createDataFrame(list(texts.items()), "doc_id bigint, text string")
    kept = [r["doc_id"] for r in corpus_pipeline.STAGES[1][1](spark, docs, sf).collect()]
    assert len(kept) == len(set(kept)) and set(kept) == plain_survivors(texts)
    empty = corpus_pipeline.stage_near_duplicates(spark, docs.filter("doc_id < 0"), sf)
    assert empty.columns == docs.columns and empty.count() == 0


def test_rest_puts_a_pair_out_about_once(spark, monkeypatch):
    """Texts that share hundreds of prefix shingles make a row or two a pair, not one for each shingle."""
    from paircuration.llm import near_copies

    draw = random.Random(5)
    bases = [[f"b{k}w{i}" for i in range(3000)] for k in range(2)]
    texts = []
    for i in range(12):  # alike about 0.71 with each other: one word of 60 replaced in each
        texts.append(" ".join(f"u{i}x{k}" if k % 60 == 5 * i else w for k, w in enumerate(bases[0])))
    for i in range(2):  # alike 0.9
        texts.append(" ".join(f"v{i}x{draw.random()}" if k % 200 == i else w for k, w in enumerate(bases[1])))
    found = [near_copies.shingles(t.encode()) for t in texts]
    alike = [(i, j) for i in range(len(texts)) for j in range(i) if len(np.intersect1d(found[i], found[j])) * 10 >= 8 * len(np.union1d(found[i], found[j]))]
    assert alike == [(13, 12)]
    rows = spark.createDataFrame([(bytes([i]), t) for i, t in enumerate(texts)], "node binary, body string")
    sets = near_copies.settle(rows.mapInArrow(near_copies._set_batches, "node binary, grams array<bigint>, bits array<bigint>"), "sets")
    met = sets.selectExpr("1L as key", "struct(node, size(grams) as size) as me")
    tree = spark.createDataFrame([], "node binary, root binary")
    rows_out, plain = [], type(sets).distinct

    def counted(df):
        if df.columns == ["a", "b"]:
            rows_out.append(df.count())
        return plain(df)

    monkeypatch.setattr(type(sets), "distinct", counted)
    pairs = near_copies._rest(met, tree, sets).collect()
    assert (bytes([12]), bytes([13])) in {(bytes(r["a"]), bytes(r["b"])) for r in pairs}
    assert rows_out[0] <= 2 * len(pairs)
