"""Boundaries, traps and invariants of the curation stages."""

import math
import os
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from paircuration.config import DIMENSIONS, DedupConfig, DetectorConfig, Stage1Config, Stage2Config, TrainingConfig
from paircuration.operators import analysis, dedup, detector, extract, greedy, metrics, split, stage1, stage2

PAIR = "pair_id bigint, repo string, name string, language string, param_names array<string>, typed_slots int, slots int, return_type string, code string, doc string, complexity int, logical_lines int"


def pair(i, name="compute_total", doc="x" * 40, complexity=2, lines=20, code="return a"):
    return (i, "r", name, "python", ["a"], 1, 2, "int", code, doc, complexity, lines)


def test_stage1_boundaries(spark):
    rows = [pair(1, doc="x" * 19), pair(2, doc="x" * 20), pair(3, doc="x" * 10_000), pair(4, doc="x" * 10_001), pair(5, complexity=0), pair(6, complexity=1), pair(7, complexity=50),
            pair(8, complexity=51), pair(9, lines=4), pair(10, lines=5), pair(11, doc=None), pair(12, doc=""), pair(13, doc="TODO: " + "x" * 30)]
    df = stage1.apply(spark.createDataFrame(rows, PAIR), mode="annotate")
    failed = {r["pair_id"]: list(r["failed"]) for r in df.collect()}
    assert {k for k, v in failed.items() if not v} == {2, 3, 6, 7, 10}
    assert failed[1] == ["doc_too_short"] and failed[4] == ["doc_too_long"] and failed[5] == ["complexity_low"] and failed[8] == ["complexity_high"]
    assert failed[9] == ["too_few_lines"] and failed[13] == ["placeholder"] and "doc_too_short" in failed[11] and failed[12] == ["doc_too_short"]


@pytest.mark.parametrize("match,dropped", [("substring", {"latest_value", "contest", "test_a", "run_test"}), ("affix", {"test_a", "run_test"}), ("boundary", {"test_a", "run_test"})])
def test_test_name_variants(spark, match, dropped):
    names = ["latest_value", "contest", "test_a", "run_test", "compute"]
    df = stage1.apply(spark.createDataFrame([pair(i, n) for i, n in enumerate(names)], PAIR), Stage1Config(test_match=match))
    assert set(names) - {r["name"] for r in df.collect()} == dropped


@pytest.mark.parametrize("match,dropped", [("prefix", {"issue_x", "hash_x", "get_x", "isReady", "get_big"}), ("boundary", {"get_x", "isReady", "get_big"}), ("boundary_and_small", {"get_x", "isReady"})])
def test_accessor_variants(spark, match, dropped):
    rows = [pair(1, "issue_x", lines=8), pair(2, "hash_x", lines=8), pair(3, "get_x", lines=8), pair(4, "isReady", lines=8), pair(5, "get_big", lines=40), pair(6, "compute", lines=8)]
    df = stage1.apply(spark.createDataFrame(rows, PAIR), Stage1Config(accessor_match=match))
    assert {r[2] for r in rows} - {r["name"] for r in df.collect()} == dropped


def test_score_range_monotone_and_scale_invariant(spark):
    draw = random.Random(1)
    rows = [tuple(draw.random() for _ in DIMENSIONS) for _ in range(50)] + [(0.0,) * 8, (1.0,) * 8]
    df = spark.createDataFrame([(i, r) for i, r in enumerate(rows)], "i int, q struct<" + ",".join(f"{d}:double" for d in DIMENSIONS) + ">")
    one = {r["i"]: r["quality"] for r in stage2.score(df).collect()}
    double = {r["i"]: r["quality"] for r in stage2.score(df, Stage2Config(weights=tuple(2 * w for w in Stage2Config().weights))).collect()}
    assert one == double and one[50] == 0 and one[51] == 10 and all(0 <= v <= 10 for v in one.values())
    up = df.withColumn("q", F.col("q").withField("types", F.least(F.lit(1.0), F.col("q.types") + 0.1)))
    assert all(r["quality"] >= one[r["i"]] for r in stage2.score(up).collect())
    with pytest.raises(ValueError):
        Stage2Config(weights=(0,) + (1,) * 7)


def test_detector_scores(spark):
    phrase, generic = "It is important to note this.", "A helper function."
    sections = "Summary here.\nParameters:\n  a: x\nReturns:\n  b\nRaises:\n  c"
    bullets = "Text\n- aaa\n- bbb\n- ccc"
    docs = ["plain", generic, bullets, phrase, sections, f"{phrase} {generic}", f"{sections}\n{bullets}\n{phrase}\n{generic}", phrase * 5, None]
    rows = spark.createDataFrame([pair(i, doc=d) for i, d in enumerate(docs)], PAIR)
    tenths = [r["ai_tenths"] for r in detector.score(rows).orderBy("pair_id").collect()]
    assert tenths == [0, 1, 2, 3, 2, 4, 8, 3, 0]
    many = [r["ai_tenths"] for r in detector.score(rows, DetectorConfig(count="per_match")).orderBy("pair_id").collect()]
    assert many[7] == 10 and many[5] == 4
    assert [r["ai_flag"] for r in detector.score(rows, DetectorConfig(tau_ai_tenths=4)).orderBy("pair_id").collect()][5]
    detector.register("short", lambda: F.length("doc") < 6, 4)
    try:
        first = detector.score(rows).orderBy("pair_id").first()
        assert first["ai_tenths"] == 4 and first["ai_matched"] == "short"
    finally:
        detector.unregister("short")


def test_published_arithmetic():
    assert abs(100 * 13358 / 52069 - 25.6) < 0.1 and abs(100 * 11602 / 13358 - 86.9) < 0.1 and abs(100 * 387 / 13358 - 2.9) < 0.1
    assert abs(100 * 8200 / 13358 - 61.4) < 0.1 and abs(100 * 3607 / 13358 - 27.0) < 0.1
    assert abs(100 * (0.0391 / 0.0302 - 1) - 29.47) < 0.02 and abs(100 * (0.0975 / 0.0786 - 1) - 24.04) < 0.02


def test_normalise_keeps_strings(spark):
    code = 'x = "a # b"  # gone\ny = \'// kept\''
    other = 'x = "a // b"; // gone\n/* gone\n too */ y = 1'
    df = spark.createDataFrame([("python", code), ("java", other), ("java", "")], "language string, code string")
    got = [r[0] for r in df.select(dedup.normalise(F.col("code"), F.col("language"))).collect()]
    assert got == ['x = "a # b" y = \'// kept\'', 'x = "a // b"; y = 1', ""]


def sequential(n, edges):
    earlier = {}
    for a, b in edges:
        earlier.setdefault(max(a, b), set()).add(min(a, b))
    kept = set()
    for i in range(n):
        if not earlier.get(i, set()) & kept:
            kept.add(i)
    return kept


@pytest.mark.parametrize("seed", range(3))
def test_greedy_equals_sequential(spark, seed):
    draw = random.Random(seed)
    n = 60
    edges = sorted({tuple(sorted(draw.sample(range(n), 2))) for _ in range(70)})
    df = spark.createDataFrame(edges, "lo bigint, hi bigint")
    got = {r["id"]: r["kept"] for r in greedy.resolve(df).collect()}
    assert {i for i in got if got[i]} == sequential(n, edges) & set(got)
    buckets = [(0, f"e{k}", i) for k, e in enumerate(edges) for i in e]
    idx = spark.createDataFrame(buckets, "band int, key string, id bigint")
    assert {r["id"]: r["kept"] for r in greedy.resolve_buckets(idx, "id").collect()} == got
    parent = list(range(n))
    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x
    for a, b in edges:
        parent[max(find(a), find(b))] = min(find(a), find(b))
    assert {r["id"]: r["root"] for r in greedy.components_keep_first(df).collect()} == {i: find(i) for i in got}


def test_chain_keeps_both_ends(spark):
    df = spark.createDataFrame([(1, 2), (2, 3)], "lo bigint, hi bigint")
    assert {r["id"] for r in greedy.resolve(df).collect() if r["kept"]} == {1, 3}
    assert {r["id"] for r in greedy.components_keep_first(df).collect() if r["kept"]} == {1}


def test_jaccard_and_estimates(spark):
    rows = [(["a"], ["b"]), (["a", "b", "c"], ["a", "b", "d"]), (list("abcde"), list("abcd")), ([], []), (["a"], ["a"])]
    df = spark.createDataFrame(rows, "a array<string>, b array<string>").select(dedup.jaccard(F.col("a"), F.col("b")))
    assert [round(r[0], 9) for r in df.collect()] == [0, 0.5, 0.8, 0, 1]
    words = [f"w{i}" for i in range(300)]
    docs = spark.createDataFrame([(i, " ".join(words[: 200 + 5 * i])) for i in range(20)], "id bigint, text string")
    sig = {r["id"]: r["signature"] for r in dedup.signatures(docs, "id", F.col("text"), DedupConfig()).collect()}
    errors = [sum(x == y for x, y in zip(sig[0], sig[i])) / 128 - 200 / (200 + 5 * i) for i in range(1, 20)]
    assert abs(sum(errors) / len(errors)) < 0.08
    assert dedup.choose_bands(0.8, 128)[0] * dedup.choose_bands(0.8, 128)[1] <= 128


def test_exact_keeps_first_whatever_the_partitions(spark):
    rows = [(i, f"t{i % 7}") for i in range(100)]
    for parts in (1, 5):
        df = spark.createDataFrame(rows, "id bigint, text string").repartition(parts)
        assert sorted(r["id"] for r in dedup.exact(df, F.col("text"), ["id"]).collect()) == list(range(7))
    assert dedup.exact(spark.createDataFrame([], "id bigint, text string"), F.col("text"), ["id"]).count() == 0


def test_exact_with_null_and_repeated_rows(spark):
    rows = [(None, "a b c"), (1, "x y z"), (2, "q r s"), (2, "q r s"), (3, None), (None, None), (None, "x y z"), (4, "")]
    got = dedup.exact(spark.createDataFrame(rows, "id bigint, text string"), F.col("text"), ["id"]).collect()
    assert sorted(((r["id"] or 0), r["text"] or "-") for r in got) == [(0, "a b c"), (1, "x y z"), (2, "q r s"), (3, "-"), (4, "-")]
    assert got[0].__fields__ == ["id", "text"]


def test_measures_of_empty_and_one_class_tables(spark):
    empty = spark.createDataFrame([], "lo int, hi int")
    assert tuple(analysis.edge_accuracy(empty, empty).first()) == (None, None)
    assert tuple(analysis.edge_accuracy(spark.createDataFrame([(1, 2)], "lo int, hi int"), empty).first()) == (None, 0.0)
    assert [r["retention"] for r in analysis.funnel([("a", empty), ("b", empty)]).collect()] == [None, None]
    scored = spark.createDataFrame([(1.0, 1), (2.0, 1)], "s double, y int")
    assert tuple(analysis.agreement(scored.limit(0), "s", "y", 1.5).first()) == (None, None, None, None)
    assert tuple(analysis.agreement(scored, "s", "y", 1.5).first())[:2] == (1.0, 0.5) and analysis.agreement(scored, "s", "y", 1.5).first()["auc"] is None
    assert tuple(analysis.agreement(scored, "s", "y", 9.0).first()) == (None, 0.0, None, None)
    assert analysis.gini(scored.limit(0), "y").first()["gini"] is None and analysis.coverage(scored.limit(0), "y").count() == 0
    assert analysis.median(spark.createDataFrame([(float(i),) for i in (5, 1, 4, 2)] + [(None,)], "v double"), "v").first()[0] == 3.0


@pytest.mark.parametrize("seed", [3, 4])
def test_bucket_pass_equals_sequential(spark, seed):
    import random

    draw = random.Random(seed)
    rows = [(band, f"k{draw.randrange(12)}", i) for i in range(40) for band in range(2)] + [(0, "hot", i) for i in range(40, 240)]
    index, kept = {}, set()
    for i in sorted({r[2] for r in rows}):
        keys = {(b, k) for b, k, j in rows if j == i}
        if not any(k in index for k in keys):
            kept.add(i)
            index.update(dict.fromkeys(keys))
    got = greedy.resolve_buckets(spark.createDataFrame(rows, "band int, key string, id bigint"), "id").collect()
    alone = {i for i in kept if i not in {r["id"] for r in got}}
    assert {r["id"] for r in got if r["kept"]} | alone == kept and len(got) == len({r["id"] for r in got})


def test_near_dedup_index_survives_a_restart(spark):
    from paircuration.sources.scratch import fresh
    from paircuration.streaming.jobs import NearDedupStream

    words = [" ".join(f"w{k}x{j}" for j in range(40)) for k in range(3)]
    folder = fresh(spark, "restart")
    one = spark.createDataFrame([(1, words[0]), (2, words[1]), (3, words[0] + " more")], "doc_id bigint, text string")
    assert sorted(r["doc_id"] for r in NearDedupStream(spark, folder=folder).step(one, 0).collect()) == [1, 2]
    two = spark.createDataFrame([(4, words[1] + " else"), (5, words[2])], "doc_id bigint, text string")
    later = NearDedupStream(spark, folder=folder)  # knows nothing but the folder
    for _ in range(2):  # a batch that is run again replaces its part
        assert [r["doc_id"] for r in later.step(two, 1).collect()] == [5]
    assert sorted(r["doc_id"] for r in later.kept().collect()) == [1, 2, 5]


def test_native_lcs_equals_bit_vectors(spark):
    import random

    draw = random.Random(8)
    rows = [(i, [draw.choice("abcd") for _ in range(draw.randrange(12))], [draw.choice("abcd") for _ in range(draw.randrange(12))]) for i in range(60)]
    df = spark.createDataFrame(rows, "pair int, cand array<string>, ref array<string>")
    for r in metrics.lcs_overlap(metrics.lcs_overlap(df).withColumnRenamed("lcs", "other").drop("precision", "recall", "lcs_f"), arrow=False).collect():
        assert r["lcs"] == r["other"]


def test_ml_crosscheck_and_retrieval_recall(spark):
    """Recall of both index variants against all pairs on planted near copies."""
    import random

    from paircuration.operators.ml_crosscheck import ml_crosscheck

    draw = random.Random(6)
    rows = []
    for k in range(60):
        base = [f"w{draw.randrange(5000)}" for _ in range(60)]
        for cut in (0, 2, 4):
            rows.append((len(rows), list(dict.fromkeys([f"x{draw.randrange(10**6)}" if j < cut else w for j, w in enumerate(base)]))))
    sets = spark.createDataFrame(rows, "id bigint, tokens array<string>")
    truth = {(a, b) for a, x in rows for b, y in rows if a < b and len(set(x) & set(y)) >= 0.8 * len(set(x) | set(y))}
    found = {(r["lo"], r["hi"]) for r in ml_crosscheck(sets, "id", 0.2).collect()}
    assert len(truth) > 100 and len(found & truth) >= 0.9 * len(truth)


def test_curation_from_files_equals_curation_of_its_pairs(spark, sf):
    from paircuration.plans import curation, pipeline
    from paircuration.sources.scratch import settle

    files = curation._files(spark, sf).withColumn("changed", F.lit("2024-01-01"))
    done = pipeline.from_files(files, "1.0", licences=["mit", "apache-2.0"], max_idle_days=600, ts="changed", before="2025-01-01")
    chosen = {r["repo"] for r in files.filter("licence IN ('mit', 'apache-2.0') AND idle_days <= 600").select("repo").distinct().collect()}
    rows = done.candidates.collect()
    assert {r["repo"] for r in rows} == chosen and len(rows) == files.filter(F.col("repo").isin(*chosen)).count()
    assert all(r["meta"]["version"] == "1.0" and r["meta"]["licence"] in ("mit", "apache-2.0") and r["meta"]["first_line"] >= 1 for r in rows)
    again = pipeline.run(settle(done.candidates.drop("meta"), "plain")).final
    assert {r["pair_id"] for r in again.collect()} == {r["pair_id"] for r in done.final.collect()}
    assert pipeline.from_files(files, "1.0", ts="changed", before="2020-01-01").candidates.count() == 0


@pytest.mark.parametrize("size", [1, 9, 10, 11])
def test_split_sizes(spark, size):
    df = split.stratified(spark.range(size).withColumn("s", F.lit("x")), "s", "id")
    counts = {r["split"]: r["count"] for r in df.groupBy("split").count().collect()}
    assert counts.get("train", 0) == math.floor(size * 0.8) and sum(counts.values()) == size


def test_packing_and_plan(spark):
    df = spark.createDataFrame([(1, 5), (2, 6), (3, 4), (4, 30)], "id bigint, n bigint").coalesce(1)
    got = {r["id"]: (r["sequence"], r["tokens"]) for r in split.pack(df, "id", "n", 10).collect()}
    assert got == {1: (0, 5), 2: (1, 6), 3: (1, 4), 4: (2, 10)}
    plan = split.step_plan(spark, 800, TrainingConfig()).collect()
    assert len(plan) == 300 and max(r["rate"] for r in plan) == 1e-4 and plan[49]["rate"] == 1e-4 and plan[-1]["rate"] == 0


@pytest.mark.parametrize("method", ["next_fit", "first_fit_decreasing"])
def test_packing_fills_and_never_overfills(spark, method):
    draw = random.Random(2)
    sizes = [draw.randrange(1, 60) for _ in range(200)] + [150]
    rows = split.pack(spark.createDataFrame(list(enumerate(sizes)), "id bigint, n bigint").coalesce(1), "id", "n", 100, method).collect()
    held = {}
    for r in rows:
        assert r["tokens"] == min(sizes[r["id"]], 100)
        held[r["sequence"]] = held.get(r["sequence"], 0) + r["tokens"]
    assert len(rows) == len(sizes) and max(held.values()) <= 100
    least = -(-sum(min(n, 100) for n in sizes) // 100)
    assert len(held) <= (2 * least if method == "next_fit" else least * 11 // 9 + 1)


def test_xxhash_signatures_are_minima(spark):
    cfg = DedupConfig(family="xxhash64", num_hashes=8, bands=2, rows=4)
    df = spark.createDataFrame([(1, "red green blue"), (2, "blue red red"), (3, "")], "id bigint, text string")
    got = {r["id"]: (r["n_tokens"], r["signature"]) for r in dedup.signatures(df, "id", F.col("text"), cfg).collect()}
    for i, words in ((1, ["red", "green", "blue"]), (2, ["blue", "red"])):
        values = [spark.createDataFrame([(w,) for w in words], "w string").select(F.xxhash64(F.lit(cfg.seed + k), "w")).collect() for k in range(8)]
        assert got[i] == (len(words), [min(r[0] for r in v) for v in values])
    assert 3 not in got


def test_metrics_extremes(spark):
    rows = [("same", "a b c d e", "a b c d e"), ("apart", "a b c d", "w x y z"), ("part", "the cat sat on the mat", "the cat lay on the mat")]
    df = spark.createDataFrame(rows, "id string, c string, r string").select("id", metrics.tokens(F.col("c")).alias("cand"), metrics.tokens(F.col("r")).alias("ref"))
    bleu = {r["id"]: r["bleu"] for r in metrics.bleu(df, "id").collect()}
    assert bleu["same"] == pytest.approx(1) and bleu["apart"] == 0
    hand = (5 / 6 * 3 / 5 * 1 / 4) ** (1 / 3)
    assert {r["id"]: r["bleu"] for r in metrics.bleu(df, "id", max_n=3).collect()}["part"] == pytest.approx(hand)
    for arrow in (True, False):
        lcs = {r["id"]: (r["lcs"], r["lcs_f"]) for r in metrics.lcs_overlap(df, arrow=arrow).collect()}
        assert lcs["same"] == (5, 1.0) and lcs["apart"] == (0, 0.0) and lcs["part"][0] == 5


def test_lcs_against_table():
    draw = random.Random(5)
    for _ in range(60):
        a, b = [[draw.choice("abcd") for _ in range(draw.randrange(12))] for _ in range(2)]
        table = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
        for i, x in enumerate(a):
            for j, y in enumerate(b):
                table[i + 1][j + 1] = table[i][j] + 1 if x == y else max(table[i][j + 1], table[i + 1][j])
        assert metrics.lcs_value(a, b) == table[-1][-1]


def test_extraction(spark):
    python = 'def f(a: int, b=1) -> str:\n    """Doc of f."""\n    if a and b:\n        return "x"\n    return ""\n'
    java = '/** Adds. */\npublic int add(int a, final String b) {\n  if (a > 0) { return "}".length(); }\n  return 0;\n}\n'
    files = spark.createDataFrame([("a.py", python, "python"), ("A.java", java, "java"), ("bad.py", "def (", "python"), ("n.py", None, "python")], "path string, source string, language string")
    rows = {r["name"]: r for r in extract.extract_functions(files).collect()}
    assert set(rows) == {"f", "add"}
    assert rows["f"]["doc"] == "Doc of f." and rows["f"]["complexity"] == 3 and rows["f"]["return_type"] == "str" and rows["f"]["params"][1]["has_default"]
    assert rows["add"]["doc"] == "Adds." and rows["add"]["complexity"] == 2 and rows["add"]["params"][0]["type"] == "int"


def test_narrow_stages_have_no_exchange(spark, sf):
    from paircuration.plans.curation import _functions

    df = detector.score(stage2.retain(stage2.score(stage2.dimensions(stage1.apply(_functions(spark, sf))))))
    assert "Exchange" not in df._jdf.queryExecution().executedPlan().toString()
    scan = spark.read.parquet(f"{sf}/documents.parquet").filter(F.col("n_chars").between(100, 2000)).select("doc_id")
    assert "PushedFilters: [IsNotNull(n_chars)" in scan._jdf.queryExecution().executedPlan().toString()


def test_entry_works_without_the_training_operators(tmp_path):
    import shutil
    import subprocess
    import sys
    from pathlib import Path

    root = Path(__file__).resolve().parents[1]
    copy = tmp_path / "repo"
    shutil.copytree(root, copy, ignore=shutil.ignore_patterns(".git", "__pycache__", "llm", "corpus_pipeline.py"))
    said = """import __spark_entry__ as e
names = e.queries()
assert {"curated_pairs", "join_asof", "stream_tumbling"} <= set(names) and set(e.oracle_sql()) <= set(names)
assert not [n for n in names if n == "pipeline" or n.startswith("op")], names
import sys
assert not [m for m in sys.modules if m.startswith("paircuration.llm.")]
print("fine", len(names))"""
    for left_over in (False, True):
        if left_over:  # a folder without modules
            (copy / "paircuration/llm/__pycache__").mkdir(parents=True)
            shutil.copy(root / "corpus_pipeline.py", copy)
        done = subprocess.run([sys.executable, "-c", said], cwd=copy, env={**os.environ, "PYTHONPATH": str(copy)}, capture_output=True, text=True)
        assert done.stdout.startswith("fine"), done.stderr
    (copy / "paircuration/llm/queries.py").write_text("import no_such_library")
    broken = subprocess.run([sys.executable, "-c", said], cwd=copy, env={**os.environ, "PYTHONPATH": str(copy)}, capture_output=True, text=True)
    assert "no_such_library" in broken.stderr  # a missing library is not hidden


def test_cosine_neighbours_are_all_found(spark):
    from paircuration.operators.cosine import neighbours

    draw = np.random.default_rng(5)
    rows = [(None, [1.0] * 16), (900, None), (901, []), (902, [0.0] * 16)]
    for size in (16, 24):
        for _ in range(150):
            a, b = np.linalg.qr(draw.normal(size=(size, 2)))[0].T
            c = draw.uniform(0.55, 0.7)
            rows += [(len(rows), [float(v) for v in a]), (len(rows) + 1, [float(v) for v in 3 * (c * a + np.sqrt(1 - c * c) * b)])]
    good = [(i, np.array(v) / np.linalg.norm(v)) for i, v in rows if i is not None and v and any(v)]
    want = {(min(i, j), max(i, j)) for n, (i, x) in enumerate(good) for j, y in good[n + 1 :] if len(x) == len(y) and x @ y >= 0.6}
    got = neighbours(spark.createDataFrame(rows, "k long, v array<double>"), "k", "v", 0.6, block=64).collect()
    assert len(got) == len(want) and {(r["lo"], r["hi"]) for r in got} == want


def test_measures_use_whole_texts(spark):
    import pandas as pd

    from paircuration import udfs

    same, a, b = " ".join(["same"] * 2048), " ".join(f"a{i}" for i in range(600)), " ".join(f"b{i}" for i in range(600))
    row = spark.createDataFrame([(f"{same} {a}", f"{same} {b}")], "x string, y string").select(metrics.tokens(F.col("x")).alias("cand"), metrics.tokens(F.col("y")).alias("ref"))
    got = metrics.lcs_overlap(row).first()
    assert len(got["cand"]) == 2648 and got["lcs"] == 2048 and abs(got["lcs_f"] - 2048 / 2648) < 1e-9
    assert abs(udfs._lcs(pd.Series([f"{same} {a}"]), pd.Series([f"{same} {b}"]))[0] - 2048 / 2648) < 1e-9


def test_source_tree_reader_takes_all_documents(spark, sf):
    from paircuration.plans import relational

    lines = [r["text"] or "" for r in spark.read.parquet(f"{sf}/documents.parquet").select("text").collect()]
    assert sum(r["chars"] for r in relational.QUERIES["source_tree_reader"](spark, sf).collect()) == sum(len(t) + 1 for t in lines)


def test_bound_leaves_out_no_link_and_few_others(spark):
    """Buckets of unlike rows make no pairs, whichever way pairs are verified; links are those of all bucket pairs."""
    from paircuration.plans import pipeline

    draw = random.Random(3)
    words = [f"w{i}" for i in range(400)]
    rows = []
    for i in range(60):
        base = draw.sample(words, 90)
        rows += [(100 * i + j, " ".join([*base[: 90 - j], *draw.sample(words, j)]), "ab"[j % 2]) for j in (0, 2, 8, 9, 10, 30)]
    common = [f"c{i}" for i in range(60)]
    rows += [(10000 + i, " ".join([*common, *[f"u{i}x{k}" for k in range(60)]]), "a") for i in range(80)]
    df = spark.createDataFrame(rows, "id bigint, text string, lang string")
    for mode in ("exact", "signature"):
        cfg = DedupConfig(verify=mode)
        sets = df.select("id", dedup.token_set(F.col("text")).alias("tokens"))
        sigs = dedup.signatures(df, "id", F.col("text"), cfg)
        for scope in (None, "lang"):
            all_met = dedup.candidates(dedup.index(sigs.join(df.select("id", "lang"), "id"), "id", cfg, scope), "id")
            whole = {tuple(r) for r in dedup.verify(all_met, sigs if mode == "signature" else sets, "id", mode, 0.8).collect()}
            assert {tuple(r) for r in pipeline.near_edges(df, "id", F.col("text"), cfg, scope).collect()} == whole and whole
            made = dedup.bounded_index(dedup.profiles(df, "id", F.col("text"), cfg, scope), "id")
            left = dedup.bounded_candidates(made, made, "id", cfg).count()
            assert len(whole) <= left < len(whole) + 0.2 * (all_met.count() - len(whole))


def test_grouped_verification_deals_a_large_component_into_blocks(spark):
    """One component of many rows, blocks of a few: each pair is verified once, with the similarity of the plain verification."""
    rows = [(i, " ".join(f"t{k}" for k in range(i, i + 30))) for i in range(40)] + [(100, "only one"), (101, "only two")]
    df = spark.createDataFrame(rows, "id bigint, text string")
    pairs = df.select(F.col("id").alias("lo")).crossJoin(df.select(F.col("id").alias("hi"))).filter("lo < hi AND hi - lo < 12")
    tokens = df.select("id", dedup.token_set(F.col("text")).alias("tokens"))
    plain = sorted(map(tuple, dedup.verify(pairs, tokens, "id", "exact", 0.5).collect()))
    assert sorted(map(tuple, dedup.verify_grouped(pairs, tokens, "id", "exact", 0.5, 7).collect())) == plain and len(plain) > 300
    assert dedup.verify_grouped(pairs.filter("lo < 0"), tokens, "id", "exact", 0.5).count() == 0


def test_all_pairs_in_blocks_equal_plain_comparison(spark, monkeypatch):
    """Neighbouring size classes, several blocks of each, wide and empty sets; no row is made for a pair that shares a common token."""
    draw = random.Random(8)
    rows = [(0, []), (1, ["only"]), (2, ["only"])]
    for k in range(25):
        base = [f"w{draw.randrange(3000)}" for _ in range(draw.choice([4, 5, 30, 37, 300, 1500]))]
        for cut in (0, 0.05, 0.1, 0.12, 0.2, 0.5):
            rows.append((len(rows), sorted({"the", *[f"x{draw.randrange(10**6)}" if j < cut * len(base) else w for j, w in enumerate(base)]})))
    plain = {(a, b, len(set(x) & set(y))) for a, x in rows for b, y in rows if a < b and x and 100 * len(set(x) & set(y)) >= 80 * len(set(x) | set(y))}
    sets = spark.createDataFrame(rows, "id bigint, tokens array<string>")
    made, settle = [], dedup.settle
    monkeypatch.setattr(dedup, "settle", lambda df, name: made.append(settle(df, name)) or made[-1])
    for block in (7, 8192):
        assert sorted(map(tuple, dedup.all_pairs(sets, "id", 80, block).collect())) == sorted(plain) and len(plain) > 30
        (pairs,) = [x for x in made if x.columns == ["lo", "hi"]]
        assert len(plain) <= pairs.count() <= 2 * len(plain)
        made.clear()


def test_ml_crosscheck_equals_the_join_of_ml(spark, monkeypatch):
    """The pairs and distances of approxSimilarityJoin, without a row for each pair of a bucket."""
    from pyspark.ml.feature import HashingTF, MinHashLSH

    from paircuration.operators import ml_crosscheck

    draw = random.Random(9)
    rows = [(0, [])]
    for k in range(30):
        base = [f"w{draw.randrange(100)}" for _ in range(50)]
        for cut in (0, 2, 4, 5, 9):
            rows.append((len(rows), list(dict.fromkeys([f"x{draw.randrange(10**6)}" if j < cut else w for j, w in enumerate(base)]))))
    sets = spark.createDataFrame(rows, "id bigint, tokens array<string>")
    vectors = HashingTF(inputCol="tokens", outputCol="v", numFeatures=1 << 20, binary=True).transform(sets.filter("size(tokens) > 0"))
    model = MinHashLSH(inputCol="v", outputCol="h", numHashTables=8, seed=7).fit(vectors)
    plain = model.approxSimilarityJoin(vectors, vectors, 0.2, "distance").selectExpr("datasetA.id as lo", "datasetB.id as hi", "distance").filter("lo < hi")
    expected, made, settle = sorted(map(tuple, plain.collect())), [], ml_crosscheck.settle
    monkeypatch.setattr(ml_crosscheck, "settle", lambda df, name: made.append(settle(df, name)) or made[-1])
    assert sorted(map(tuple, ml_crosscheck.ml_crosscheck(sets, "id", 0.2).collect())) == expected and len(expected) > 50
    (pairs,) = [x for x in made if x.columns == ["lo", "hi"]]
    assert pairs.count() <= 3 * len(expected)


def test_common_buckets_meet_by_size_and_in_blocks(spark, monkeypatch):
    """One bucket of all rows gives each pair that the bound allows once, without a join of the bucket with itself."""
    draw = random.Random(21)
    rows = []
    for k in range(20):
        base = [f"w{draw.randrange(3000)}" for _ in range(draw.choice([5, 20, 60, 200]))]
        for cut in (0, 1, 3, 9):
            rows.append((f"{draw.randrange(10**6):06}-{len(rows)}", list(dict.fromkeys([f"x{draw.randrange(10**6)}" if j < cut else w for j, w in enumerate(base)]))))
    made = dedup.set_profiles(spark.createDataFrame(rows, "id string, tokens array<string>"), "id").withColumn("keys", F.array(F.lit(1).cast("bigint"), F.xxhash64("n"))).cache()
    plain = made.alias("x").join(made.alias("y"), F.expr(f"x.id < y.id AND {dedup.bound(dedup.MAP, DedupConfig())}")).selectExpr("x.id", "y.id as other")
    expected = sorted(map(tuple, plain.collect()))
    truth = {(a, b) for a, x in rows for b, y in rows if a < b and len(set(x) & set(y)) >= 0.8 * len(set(x) | set(y))}
    for block in (16384, 11):
        found = dedup.bounded_meetings(made, "id", 0.8, block)
        assert sorted(map(tuple, found.collect())) == expected and truth <= set(expected) and len(truth) > 20
    monkeypatch.setattr(dedup, "bounded_candidates", None)
    from paircuration.operators.ml_crosscheck import ml_crosscheck

    assert {(r["lo"], r["hi"]) for r in ml_crosscheck(spark.createDataFrame(rows, "id string, tokens array<string>"), "id", 0.2).collect()} <= truth


def test_ordered_pass_of_a_chain_takes_few_rounds(spark, monkeypatch):
    """Whole components at once or, above the limit, in rounds: the same verdicts; a long chain settles few tables."""
    draw, made, settle = random.Random(12), [], greedy.settle
    monkeypatch.setattr(greedy, "settle", lambda df, name="state": made.append(1) or settle(df, name))
    pairs = {(i, i + 1) for i in range(60)} | {tuple(sorted(draw.sample(range(100, 130), 2))) for _ in range(40)} | {(200, 201)}
    dropped = set()
    for lo, hi in sorted(pairs, key=lambda p: p[1]):
        if lo not in dropped:
            dropped.add(hi)
    expected = {i: i not in dropped for p in pairs for i in p}
    edges = spark.createDataFrame([*pairs, (200, 201)], "lo bigint, hi bigint")
    found = greedy.resolve(edges).collect()
    assert len(found) == len(expected) and {r["id"]: r["kept"] for r in found} == expected and len(made) < 60
    found = greedy.resolve(edges.filter("lo >= 100"), most=20).collect()
    assert {r["id"]: r["kept"] for r in found} == {i: k for i, k in expected.items() if i >= 100}
    named = greedy.resolve(edges.selectExpr("lpad(lo, 3, '0') as lo", "lpad(hi, 3, '0') as hi")).collect()
    assert {int(r["id"]): r["kept"] for r in named} == expected
    assert greedy.resolve(edges.filter("lo < 0")).count() == 0


def test_estimates_move_signatures_by_group(spark, sf, monkeypatch):
    """All candidate pairs with the estimates of the plain verification, which moves two signatures with each pair."""
    from paircuration.plans import curation

    sigs, plain, calls = curation._signatures(spark, sf), dedup.verify, []
    expected = plain(dedup.candidates(dedup.index(sigs, "doc_id"), "doc_id"), sigs, "doc_id", "signature", 0.0)
    monkeypatch.setattr(dedup, "verify", lambda *a: calls.append(1) or plain(*a))
    found = curation.minhash_estimates(spark, sf)
    assert sorted(map(tuple, found.collect())) == sorted(map(tuple, expected.collect())) and not calls


def test_estimates_are_made_in_buckets_without_a_table_of_pairs(spark, monkeypatch):
    """Hot buckets dealt into blocks and bundled small ones give each pair once; no candidates are settled or searched for components."""
    draw = random.Random(3)
    rows = []
    for k in range(12):
        base = [f"w{draw.randrange(4000)}" for _ in range(40)]
        for _ in range(30 if k == 0 else draw.randrange(1, 9)):
            rows.append((len(rows), " ".join(draw.choice(base) if draw.random() < 0.7 else f"w{draw.randrange(4000)}" for _ in range(60)) if k else " ".join(base[:38] + [f"x{len(rows)}"])))
    cfg = DedupConfig()
    sigs = dedup.signatures(spark.createDataFrame([*rows, (9000, "")], "id bigint, text string"), "id", F.col("text"), cfg).cache()
    expected = sorted(map(tuple, dedup.verify(dedup.candidates(dedup.index(sigs, "id", cfg), "id"), sigs, "id", "signature", 0.0).collect()))
    made, settle = [], dedup.settle
    monkeypatch.setattr(dedup, "settle", lambda df, name: made.append(name) or settle(df, name))
    monkeypatch.setattr(greedy, "components_keep_first", None)
    for block, most in ((1024, 500_000), (7, 40), (4, 1)):
        assert sorted(map(tuple, dedup.bucket_estimates(sigs, "id", cfg, block, most).collect())) == expected and len(expected) > 435
    assert set(made) == {"shared", "members"}
    monkeypatch.setattr(dedup, "MOVED", 300)
    assert sorted(map(tuple, dedup.bucket_estimates(sigs, "id", cfg, 7, 40).collect())) == expected
    assert dedup.bucket_estimates(sigs.filter("id = 0"), "id", cfg).count() == 0


def test_prefix_join_equals_plain_comparison_and_makes_few_pairs(spark, monkeypatch):
    """Sets that share rare tokens but are unlike make no pair; the pairs and counts are those of the plain comparison."""
    draw = random.Random(14)
    rows = [(0, []), (1, ["only"]), (2, ["only"])]
    for k in range(25):
        rare = [f"r{k}x{j}" for j in range(8)]
        base = [f"w{draw.randrange(30000)}" for _ in range(draw.choice([30, 37, 90, 300]))]
        for cut in (0, 0.05, 0.1, 0.12, 0.2, 0.5, 1, 1, 1, 1):
            rows.append((len(rows), sorted({"the", *rare, *[f"w{draw.randrange(30000)}" if j < cut * len(base) else w for j, w in enumerate(base)]})))
    plain = {(a, b, len(set(x) & set(y))) for a, x in rows for b, y in rows if a < b and x and 100 * len(set(x) & set(y)) >= 80 * len(set(x) | set(y))}
    sets = spark.createDataFrame(rows, "id bigint, tokens array<string>")
    made, settle = [], dedup.settle
    monkeypatch.setattr(dedup, "settle", lambda df, name: made.append(settle(df, name)) or made[-1])
    assert sorted(map(tuple, dedup.prefix_join(sets, "id", 80).collect())) == sorted(plain) and len(plain) > 30
    (pairs,) = [x for x in made if x.columns == ["lo", "hi"]]
    assert pairs.count() <= 2 * len(plain)
    assert dedup.prefix_join(sets.filter("id = 0"), "id", 80).count() == 0


@pytest.mark.parametrize("family", ["affine31", "xxhash64"])
def test_near_dedup_stream_makes_no_pairs_of_unlike_rows(spark, monkeypatch, family):
    """Batches keep what one ordered pass over all rows keeps, and unlike rows of one bucket make no pair, inside a batch or with the index."""
    from paircuration.streaming import jobs

    draw, cfg = random.Random(17), DedupConfig(family=family)
    rows, common = [], [f"c{i}" for i in range(60)]
    for k in range(12):
        base = [f"w{draw.randrange(10**6)}" for _ in range(60)]
        rows += [" ".join([*base[j:], *[f"x{draw.randrange(10**6)}" for _ in range(j)]]) for j in (0, 1, 2, 9)]
    rows += [" ".join([*common, *[f"u{i}x{k}" for k in range(60)]]) for i in range(60)]
    draw.shuffle(rows)
    df = spark.createDataFrame(list(enumerate(rows)), "doc_id bigint, text string")
    sigs, tokens = dedup.signatures(df, "doc_id", F.col("text"), cfg), df.select("doc_id", dedup.token_set(F.col("text")).alias("tokens"))
    met = dedup.candidates(dedup.index(sigs, "doc_id", cfg), "doc_id")
    edges = [(r["lo"], r["hi"]) for r in dedup.verify(met, tokens, "doc_id", "exact", 0.8).collect()]
    made, settle = [], jobs.settle
    monkeypatch.setattr(jobs, "settle", lambda d, name="state": made.append(settle(d, name)) or made[-1])
    state = jobs.NearDedupStream(spark, cfg)
    for i in range(2):
        state.step(df.filter(f"doc_id % 108 >= {54 * i} AND doc_id % 108 < {54 * i + 54}"), i)
    assert {r["doc_id"] for r in state.kept().collect()} == sequential(len(rows), edges) and len(edges) > 20
    pairs = sum(x.count() for x in made if x.columns == ["lo", "hi"])
    assert 20 < pairs <= 2 * len(edges) < met.count()


def test_retrieval_in_blocks_equals_all_proposals(spark):
    """Several blocks of both sides: for each row the best of all that share a bucket, ties to the smaller id; no join makes a row for a proposal."""
    from paircuration.operators import generators

    draw, cfg = random.Random(21), DedupConfig(num_hashes=64, bands=32, rows=2)
    texts = [" ".join(draw.choice("abcdefghijklmnop") + str(draw.randrange(4)) for _ in range(25)) for _ in range(120)] + ["", "zz1 zz2"]
    kind = "pair_id bigint, code string, doc string, name string, param_names array<string>"
    df = spark.createDataFrame([(i, t, f"doc {i}" if i % 7 else None, "getThing", ["p"]) for i, t in enumerate(texts)], kind)
    train, test = df.filter("pair_id < 90"), df.filter("pair_id >= 90")
    keys = {r["pair_id"]: r["keys"] for r in dedup.profiles(df, "pair_id", F.col("code"), cfg).collect()}
    bag, expected, proposals = {i: set(t.split()) for i, t in enumerate(texts)}, {}, 0
    for i in range(90, len(texts)):
        met = [j for j in range(90) if i in keys and any(a == b for a, b in zip(keys[i], keys[j]))]
        best = max(met, key=lambda j: (len(bag[i] & bag[j]) / len(bag[i] | bag[j]), -j), default=None)
        proposals += len(met)
        expected[i] = f"doc {best}" if best is not None and best % 7 else "get thing p"
    for block in (7, 8192):
        got = generators.retrieve(train, test, block=block)
        assert {r["pair_id"]: r["generated"] for r in got.collect()} == expected and proposals > 200
    assert {r["generated"] for r in generators.retrieve(train.filter("pair_id < 0"), test).collect()} == {"get thing p"}


def test_first_rows_are_those_of_the_whole_order(spark):
    from paircuration.operators import split

    df, key = spark.range(500), F.md5(F.col("id").cast("string"))
    for n in (0, 1, 333, 500, 900):
        assert sorted(r[0] for r in split.first_rows(df, key, n).collect()) == sorted(r[0] for r in df.orderBy(key).limit(n).collect())
    plan = split.first_rows(df, key, 333)._jdf.queryExecution().optimizedPlan().toString()
    assert "Filter" in plan.split("Sort")[-1]  # only one range of digests is sorted


def test_band_choice_follows_the_sets_of_the_table(spark, tmp_path):
    """The choice is the best of all options over the similarities that the table's sets can have, and changes with the table."""
    from paircuration.plans import curation

    found = []
    for sizes in ((3, 3, 4), (40, 90, 200)):
        folder = tmp_path / str(sizes[0])
        texts = [(i, " ".join(f"w{j}" for j in range(n))) for i, n in enumerate(sizes)] + [(8, ""), (9, None)]
        spark.createDataFrame(texts, "doc_id bigint, text string").write.parquet(f"{folder}/documents.parquet")
        cells = [0.0] * 200
        for n in sizes:
            for c in range(n + 1):
                cells[min(199, 200 * c // (2 * n - c))] += 1 / (n + 1)
        found.append({r["tau"]: (r["bands"], r["rows"]) for r in curation.lsh_band_choice(spark, str(folder)).collect()})
        for tau, cut in ((0.5, 100), (0.8, 160)):
            def wrong(o):
                miss = [(1 - ((i + 0.5) / 200) ** o[1]) ** o[0] for i in range(200)]
                return sum(w * (1 - m if i < cut else m) for i, (w, m) in enumerate(zip(cells, miss)))
            assert wrong(found[-1][tau]) <= min(wrong((b, r)) for r in range(1, 129) for b in range(1, 128 // r + 1)) + 1e-12
    assert found[0] != found[1]


def test_prefix_join_in_parts_holds_one_exchange_at_a_time(spark, monkeypatch):
    """Parts, one row a set and only first rows: the pairs of the plain comparison; no settled table has a row for each token of a prefix."""
    draw = random.Random(15)
    rows = [(0, []), (1, ["only"]), (2, ["only"])]
    for _ in range(20):
        base = [f"w{draw.randrange(2000)}" for _ in range(draw.choice([20, 60, 200]))]
        for cut in (0, 0.05, 0.1, 0.3, 1):
            rows.append((len(rows), sorted({f"w{draw.randrange(2000)}" if j < cut * len(base) else w for j, w in enumerate(base)})))
    left = {i for i, _ in rows if i % 7}
    plain = {(a, b, len(set(x) & set(y))) for a, x in rows for b, y in rows if a < b and x and {a, b} <= left and 100 * len(set(x) & set(y)) >= 80 * len(set(x) | set(y))}
    sets = spark.createDataFrame(rows, "id bigint, tokens array<string>")
    firsts = spark.createDataFrame([(i,) for i in left], "id bigint")
    made, settle, parts, settle_all = [], dedup.settle, [], dedup.settle_all
    monkeypatch.setattr(dedup, "settle", lambda df, name: made.append((name, settle(df, name))) or made[-1][1])
    monkeypatch.setattr(dedup, "discard", lambda *tables: None)
    for part in (4_000_000, 100):
        made.clear()
        monkeypatch.setattr(dedup, "PART", part)
        monkeypatch.setattr(dedup, "settle_all", lambda dfs, name: settle_all((parts.append(name) or df for df in dfs), name))
        found = dedup.verify_grouped(dedup.prefix_pairs(sets, "id", 80, firsts), sets, "id", "common", 80)
        assert sorted(map(tuple, found.collect())) == sorted(plain) and len(plain) > 30
        (prefix,) = [t for name, t in made if name == "prefix"]
        assert prefix.count() == len([i for i, x in rows if x and i in left])
    assert 3 < len(parts) <= dedup.PARTS


def test_settled_tables_leave_no_shuffle_files(spark):
    import gc
    import time

    from paircuration.sources import scratch

    def files():
        found = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
        return {f for f in (found.apply(i).getName() for i in range(found.length())) if f.startswith("shuffle_")}

    def waited(left):
        for _ in range(100):
            if not left():
                return True
            time.sleep(0.1)

    gc.disable()
    try:
        before, frame = files(), spark.range(1000).selectExpr("id % 7 as k").groupBy("k").count()
        table = scratch.settle(frame)
        assert waited(lambda: files() - before) and sorted(r["k"] for r in table.collect()) == list(range(7))
    finally:
        gc.enable()
    assert spark.conf.get(scratch.CLEANUP, None) in (None, "false")
    scratch.discard(table, scratch.settle(spark.range(3).filter("id < 0")))
    folder = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(table.inputFiles()[0]).getParent() if table.inputFiles() else None
    assert folder is None or not folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(folder)


def test_dedup_accuracy_settles_no_texts_and_deletes_what_is_used_up(spark, sf):
    from paircuration.plans import curation
    from paircuration.sources import scratch

    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{scratch.shared_dir(spark)}/{spark.sparkContext.applicationId}")
    at = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())

    def folders():
        return {x.getPath().getName() for x in at.listStatus(path)} if at.exists(path) else set()

    before = folders()
    assert tuple(curation.dedup_accuracy(spark, sf).first()) == (1.0, 1.0)
    left = {x.rsplit("-", 1)[0] for x in folders() - before}
    assert "sets" in left and not left & {"texts", "profiles", "members", "bands", "prefix", "nodes"}
