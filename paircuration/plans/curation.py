"""Workload queries of the curation engine with their SQL counterparts.

QUERIES maps a name to a function of (spark, sf_dir); ORACLES maps a name to SQL over the same tables.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from paircuration import carriers
from paircuration.config import DIMENSIONS, DedupConfig, DetectorConfig, Stage1Config, Stage2Config, TrainingConfig
from paircuration.functions import rules as R
from paircuration.functions.dialect import DUCK
from paircuration.operators import analysis, dedup, detector, extract, generators, greedy, metrics, split, stage1, stage2
from paircuration.plans import oracle_parts as P
from paircuration.plans import pipeline
from paircuration.sources.scratch import discard, settle
from paircuration.sources.tables import load

QUERIES, ORACLES = {}, {}


def query(name: str, sql: str | None = None):
    def keep(fn):
        QUERIES[name] = fn
        if sql:
            ORACLES[name] = sql
        return fn
    return keep


_rendered: dict[tuple, tuple[str, DataFrame]] = {}


def _functions(spark: SparkSession, sf: str) -> DataFrame:
    """The ingested pair table: rendered once per application and state of the input, then read as a table by every workload.

    The table also keeps the optimiser from folding the renderer's expressions into those of the stages.  It is rendered
    again if the documents' files have changed or the table has been released.
    """
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    where = jvm.org.apache.hadoop.fs.Path(f"{sf}/documents.parquet")
    state = [(str(f.getPath()), f.getLen(), f.getModificationTime()) for f in where.getFileSystem(conf).listStatus(where)]
    key = (spark.sparkContext.applicationId, sf, tuple(sorted(state)))
    if key in _rendered:
        made = jvm.org.apache.hadoop.fs.Path(_rendered[key][0])
        if not made.getFileSystem(conf).exists(made):
            del _rendered[key]
    if key not in _rendered:
        table = settle(carriers.function_pairs(spark, sf), "pairs")
        _rendered[key] = (table.inputFiles()[0].rsplit("/", 1)[0], table)
    return _rendered[key][1]


def _collapsed(text="text"):
    return F.trim(F.regexp_replace(text, "[ \t\n\r]+", " "))


def _texts(spark: SparkSession, sf: str) -> DataFrame:
    """Documents after exact removal, settled: the input of all near-duplicate workloads."""
    docs = load(spark, sf, "documents", ["doc_id", "text"])
    return settle(dedup.exact(docs, _collapsed(), ["doc_id"]), "texts")


TEXT = P.COLLAPSE.format("text")
FIRSTS = P.exact("documents", "firsts", "doc_id", TEXT)
NEAR = [*FIRSTS, *P.near("firsts", "doc_id", "text")]
CFG = DedupConfig()

# ---- carriers -------------------------------------------------------------------------------------------------------

query("function_pairs", carriers.function_oracle())(carriers.function_pairs)
query("page_extract", carriers.page_sql(DUCK))(carriers.page_pairs)
query("reply_pairs", carriers.reply_sql())(carriers.reply_pairs)

# ---- stage 1 --------------------------------------------------------------------------------------------------------


def _rule_sql(cfg: Stage1Config) -> str:
    fails = list(R.stage1(DUCK, cfg))
    rows = []
    for i, k in enumerate(fails):
        before = "".join(f" AND NOT f_{b}" for b in fails[:i])
        rows.append(f"SELECT '{k}' AS rule, count(*) FILTER (f_{k}) AS failing, count(*) FILTER (f_{k}{before}) AS first FROM judged")
    return P.statement([*P.functions(), *P.stage1(cfg)], f"SELECT * FROM ({' UNION ALL '.join(rows)}) WHERE failing > 0")


STAGE1_VARIANTS = {
    "stage1_rules": Stage1Config(), "stage1_rules_table_profile": Stage1Config.table(),
    "stage1_rules_prefix_substring": Stage1Config(accessor_match="prefix", test_match="substring"),
    "stage1_rules_boundary": Stage1Config(accessor_match="boundary", test_match="boundary", placeholder_case_sensitive=False, max_logical_lines=60),
}
for _name, _cfg in STAGE1_VARIANTS.items():
    query(_name, _rule_sql(_cfg))(lambda spark, sf, cfg=_cfg: analysis.rule_counts(stage1.apply(_functions(spark, sf), cfg, "annotate")))


@query("stage1_survivors", P.statement([*P.functions(), *P.stage1()], "SELECT pair_id, name, language FROM stage1"))
def stage1_survivors(spark, sf):
    return stage1.apply(_functions(spark, sf)).select("pair_id", "name", "language")


@query("stage1_length", "SELECT count(*) FILTER (length(text) < 20) AS too_short, count(*) FILTER (length(text) > 10000) AS too_long, count(*) FILTER (length(text) BETWEEN 20 AND 10000) AS passing FROM documents")
def stage1_length(spark, sf):
    n = F.char_length("text")
    return load(spark, sf, "documents", ["text"]).agg(F.count_if(n < 20).alias("too_short"), F.count_if(n > 10000).alias("too_long"), F.count_if(n.between(20, 10000)).alias("passing"))


# ---- stage 2 --------------------------------------------------------------------------------------------------------

def _scored(spark, sf, cfg=Stage2Config()):
    return stage2.score(stage2.dimensions(stage1.apply(_functions(spark, sf))), cfg)


_DIMS = ", ".join(f"round(d_{n}, 6) AS {n}" for n in DIMENSIONS)
_SCORED = [*P.functions(), *P.stage1(), *P.scored()]


@query("quality_scores", P.statement(_SCORED, f"SELECT pair_id, {_DIMS}, quality FROM scored"))
def quality_scores(spark, sf):
    return _scored(spark, sf).select("pair_id", *[F.round(f"q.{n}", 6).alias(n) for n in DIMENSIONS], "quality")


@query("quality_scores_equal_weights", P.statement([*P.functions(), *P.stage1(), *P.scored(Stage2Config.equal())], "SELECT pair_id, quality FROM scored"))
def quality_scores_equal(spark, sf):
    return _scored(spark, sf, Stage2Config.equal()).select("pair_id", "quality")


@query("quality_retained", P.statement(_SCORED, "SELECT pair_id, quality FROM scored WHERE quality >= 6.0"))
def quality_retained(spark, sf):
    return stage2.retain(_scored(spark, sf)).select("pair_id", "quality")


_STEPS = [i / 2 for i in range(21)]


@query("quality_sweep", P.statement(_SCORED, "SELECT threshold, count(*) FILTER (quality >= threshold) AS kept FROM scored, (SELECT cast(unnest(range(21)) / 2.0 AS DOUBLE) AS threshold) GROUP BY threshold"))
def quality_sweep(spark, sf):
    return analysis.sweep(_scored(spark, sf), "quality", _STEPS)


_TEXT_DIMS = ("clarity", "structure")


def _text_quality_sql(cfg: Stage2Config) -> str:
    dims = R.dimensions(DUCK)
    text = R.quality(DUCK, cfg, _TEXT_DIMS)
    raw = ", ".join(f"cast({dims[n]} AS DOUBLE) AS {n}" for n in _TEXT_DIMS)
    return f"SELECT pair_id, {text} AS quality FROM (SELECT *, {raw} FROM (SELECT doc_id AS pair_id, source AS name, text AS doc, cast(NULL AS VARCHAR[]) AS param_names FROM documents) t) s"


def _text_quality(spark, sf, cfg=Stage2Config()):
    rows = load(spark, sf, "documents").select(F.col("doc_id").alias("pair_id"), F.col("source").alias("name"), F.col("text").alias("doc"))
    return stage2.score(stage2.dimensions(rows, _TEXT_DIMS), cfg, _TEXT_DIMS).select("pair_id", "quality")


for _name, _cfg in {"text_quality": Stage2Config(), "text_quality_missing_zero": Stage2Config(missing="zero")}.items():
    query(_name, _text_quality_sql(_cfg))(lambda spark, sf, cfg=_cfg: _text_quality(spark, sf, cfg))


@query("label_agreement", f"""
WITH s AS ({_text_quality_sql(Stage2Config())}), j AS (SELECT s.quality AS q, l.quality AS y FROM s JOIN labels l ON l.doc_id = pair_id),
hits AS (SELECT count(*) FILTER (q >= 6 AND y = 1) AS tp, count(*) FILTER (q >= 6 AND y <> 1) AS fp, count(*) FILTER (q < 6 AND y = 1) AS fn FROM j),
ranks AS (SELECT y, (rank() OVER (ORDER BY q) + (count(*) OVER (PARTITION BY q) - 1) / 2.0) AS r FROM j),
auc AS (SELECT (sum(r) FILTER (y = 1) - count(*) FILTER (y = 1) * (count(*) FILTER (y = 1) + 1) / 2.0) / (count(*) FILTER (y = 1) * count(*) FILTER (y <> 1)) AS auc FROM ranks)
SELECT tp / (tp + fp) AS "precision", tp / (tp + fn) AS recall, 2 * (tp / (tp + fp)) * (tp / (tp + fn)) / ((tp / (tp + fp)) + (tp / (tp + fn))) AS f1, round(auc, 9) AS auc FROM hits, auc""")
def label_agreement(spark, sf):
    labels = load(spark, sf, "labels").select(F.col("doc_id").alias("pair_id"), F.col("quality").alias("label"))
    return analysis.agreement(_text_quality(spark, sf).join(labels, "pair_id"), "quality", "label", 6.0)


# ---- stage 3 --------------------------------------------------------------------------------------------------------

@query("exact_dedup", P.statement(FIRSTS, "SELECT doc_id FROM firsts"))
def exact_dedup(spark, sf):
    return dedup.exact(load(spark, sf, "documents", ["doc_id", "text"]), _collapsed(), ["doc_id"]).select("doc_id")


@query("exact_dedup_confirmed", P.statement(FIRSTS, "SELECT doc_id FROM firsts"))
def exact_dedup_confirmed(spark, sf):
    return dedup.exact_confirmed(load(spark, sf, "documents", ["doc_id", "text"]), _collapsed(), ["doc_id"]).select("doc_id")


@query("exact_groups", f"SELECT doc_id, min(doc_id) OVER w AS dup_of, count(*) OVER w AS group_size FROM documents WINDOW w AS (PARTITION BY md5({TEXT}))")
def exact_groups(spark, sf):
    return dedup.exact_report(load(spark, sf, "documents", ["doc_id", "text"]), _collapsed(), "doc_id")


_PER_LANG = P.exact("documents", "firsts", "doc_id", f"lang || ':' || {TEXT}")


@query("exact_dedup_within_language", P.statement(_PER_LANG, "SELECT doc_id FROM firsts"))
def exact_dedup_within_language(spark, sf):
    docs = load(spark, sf, "documents", ["doc_id", "lang", "text"])
    return dedup.exact(docs, F.concat_ws(":", "lang", _collapsed()), ["doc_id"]).select("doc_id")


@query("exact_dedup_within_repo", P.statement(P.exact("documents", "firsts", "doc_id", f"source || ':' || {TEXT}"), "SELECT doc_id FROM firsts"))
def exact_dedup_within_repo(spark, sf):
    docs = load(spark, sf, "documents", ["doc_id", "source", "text"])
    return dedup.exact(docs, F.concat_ws(":", "source", _collapsed()), ["doc_id"], "sha2").select("doc_id")


@query("function_normalised", P.statement(P.functions(), f"SELECT pair_id, md5({P.BARE_CODE}) AS digest FROM fp"))
def function_normalised(spark, sf):
    return _functions(spark, sf).select("pair_id", F.md5(dedup.normalise(F.col("code"), F.col("language"))).alias("digest"))


@query("token_sets", "SELECT doc_id, len(t) AS n_tokens, md5(array_to_string(list_sort(t), ' ')) AS digest FROM (SELECT doc_id, list_distinct(regexp_extract_all(lower(text), '[a-z0-9_]+')) AS t FROM documents)")
def token_sets(spark, sf):
    t = dedup.token_set(F.col("text"))
    return load(spark, sf, "documents", ["doc_id", "text"]).select("doc_id", t.alias("t")).select("doc_id", F.size("t").cast("bigint").alias("n_tokens"), F.md5(F.array_join(F.array_sort("t"), " ")).alias("digest"))


def _sets(spark, sf):
    return _texts(spark, sf).select("doc_id", dedup.token_set(F.col("text")).alias("tokens"))


_PAIR_SQL = P.statement([*FIRSTS, ("sets", "SELECT doc_id AS id, list_distinct(regexp_extract_all(lower(text), '[a-z0-9_]+')) AS tokens FROM firsts"),
                         ("flat", "SELECT id, len(tokens) AS n, unnest(tokens) AS token FROM sets"),
                         ("common", "SELECT a.id AS lo, b.id AS hi, count(*) AS common, any_value(a.n) AS na, any_value(b.n) AS nb FROM flat a JOIN flat b ON a.token = b.token AND a.id < b.id AND 100 * least(a.n, b.n) >= 80 * greatest(a.n, b.n) GROUP BY ALL")],
                        "SELECT lo, hi, common FROM common WHERE 100 * common >= 80 * (na + nb - common)").replace("GROUP BY ALL", "GROUP BY a.id, b.id")


@query("jaccard_pairs", _PAIR_SQL)
def jaccard_pairs(spark, sf):
    return dedup.prefix_join(settle(_sets(spark, sf), "sets"), "doc_id", 80)


@query("jaccard_pairs_brute", _PAIR_SQL)
def jaccard_pairs_brute(spark, sf):
    return dedup.all_pairs(_sets(spark, sf), "doc_id", 80)


def _signatures(spark, sf, cfg=CFG):
    texts = _texts(spark, sf)
    made = settle(dedup.signatures(texts, "doc_id", F.col("text"), cfg), "signatures")
    discard(texts)
    return made


@query("minhash_signatures", P.statement(NEAR, "SELECT id AS doc_id, n_tokens, md5(array_to_string(signature, ',')) AS digest FROM sig"))
def minhash_signatures(spark, sf):
    return dedup.signatures(_texts(spark, sf), "doc_id", F.col("text"), CFG).select("doc_id", "n_tokens", F.md5(F.array_join(F.col("signature").cast("array<string>"), ",")).alias("digest"))


@query("minhash_signatures_xxhash")
def minhash_signatures_xxhash(spark, sf):
    return dedup.signatures(_texts(spark, sf), "doc_id", F.col("text"), DedupConfig(family="xxhash64"))


@query("minhash_estimates", P.statement([*NEAR, *P.edges("signature", 0.0)], "SELECT lo, hi, sim AS estimate FROM edges"))
def minhash_estimates(spark, sf):
    return dedup.bucket_estimates(_signatures(spark, sf), "doc_id", CFG).withColumnRenamed("sim", "estimate")


@query("lsh_index", P.statement(NEAR, "SELECT id AS doc_id, band, key FROM idx"))
def lsh_index(spark, sf):
    return dedup.index(_signatures(spark, sf), "doc_id", CFG).select("doc_id", F.col("band").cast("bigint").alias("band"), "key")


@query("lsh_bucket_report", P.statement(NEAR, "SELECT members, count(*) AS buckets FROM (SELECT count(*) AS members FROM idx GROUP BY band, key) GROUP BY members"))
def lsh_bucket_report(spark, sf):
    return dedup.bucket_report(dedup.index(_signatures(spark, sf), "doc_id", CFG))


@query("lsh_candidates", P.statement(NEAR, "SELECT lo, hi FROM cand"))
def lsh_candidates(spark, sf):
    return dedup.candidates(dedup.index(_signatures(spark, sf), "doc_id", CFG), "doc_id")


_BANDS = """WITH o AS (SELECT b, r FROM range(1, 129) x(r), range(1, 129) y(b) WHERE b * r <= 128), t AS (SELECT unnest([100, 120, 140, 160, 180]) AS cut),
sizes AS (SELECT m, count(*) AS docs FROM (SELECT len(list_distinct(regexp_extract_all(lower(text), '[a-z0-9_]+'))) AS m FROM documents) WHERE m > 0 GROUP BY m),
w AS (SELECT i, sum(docs::DOUBLE / (m + 1)) AS w FROM (SELECT m, docs, least(199, (200 * c) // (2 * m - c)) AS i FROM (SELECT m, docs, unnest(range(0, m + 1)) AS c FROM sizes)) GROUP BY i),
p AS (SELECT cut, b, r, i, w, (1 - ((i + 0.5) / 200.0::DOUBLE) ** r) ** b AS miss FROM t, o, w),
a AS (SELECT cut, b, r, sum(w * CASE WHEN i < cut THEN 0.5 * (1 - miss) ELSE 0.5 * miss END) AS area FROM p GROUP BY cut, b, r)
SELECT cut / 200.0::DOUBLE AS tau, b::INT AS bands, r::INT AS rows FROM (SELECT *, row_number() OVER (PARTITION BY cut ORDER BY area, b, r) AS place FROM a) WHERE place = 1"""


@query("lsh_band_choice", _BANDS)
def lsh_band_choice(spark, sf):
    """Bands and rows for each threshold, by the similarities that the documents' token sets can have."""
    sizes = load(spark, sf, "documents", ["text"]).select(F.size(dedup.token_set(F.col("text"))).alias("size")).groupBy("size").agg(F.count(F.lit(1)).alias("sets"))
    cells = dedup.similarity_cells(sizes)
    rows = [(t, *dedup.choose_bands(t, 128, cells=cells)) for t in (0.5, 0.6, 0.7, 0.8, 0.9)]
    return spark.createDataFrame(rows, "tau double, bands int, rows int")


def _edges(spark, sf, mode):
    return pipeline.near_edges(load(spark, sf, "documents", ["doc_id", "text"]), "doc_id", F.col("text"), DedupConfig(verify=mode), unique=_collapsed())


def _greedy(spark, sf, mode):
    if mode == "none":
        return pipeline.near_dedup(_texts(spark, sf), "doc_id", F.col("text"), DedupConfig(verify=mode)).select("doc_id")
    gone = greedy.resolve(_edges(spark, sf, mode)).filter("NOT kept").select(F.col("id").alias("doc_id"))
    return exact_dedup(spark, sf).join(gone, "doc_id", "left_anti")


for _mode in ("none", "signature", "exact"):
    _sim = ", round(sim, 9) AS sim" if _mode != "none" else ""
    query(f"lsh_edges_{_mode}", P.statement([*NEAR, *P.edges(_mode)], f"SELECT lo, hi{_sim} FROM edges"))(
        lambda spark, sf, mode=_mode: _edges(spark, sf, mode).select("lo", "hi", *([F.round("sim", 9).alias("sim")] if mode != "none" else [])))
    query(f"near_dedup_greedy_{_mode}", P.statement([*NEAR, *P.edges(_mode), *P.greedy()], "SELECT doc_id FROM firsts WHERE doc_id NOT IN (SELECT id FROM verdicts WHERE NOT kept)"))(
        lambda spark, sf, mode=_mode: _greedy(spark, sf, mode))


@query("near_dedup_components", P.statement([*NEAR, *P.edges("exact"), *P.components()], "SELECT id, root, kept FROM verdicts"))
def near_dedup_components(spark, sf):
    return greedy.components_keep_first(_edges(spark, sf, "exact")).select("id", "root", "kept")


_COMPARED = [*NEAR, *P.edges("exact"), *P.greedy(), ("reach", P.components()[0][1]), ("least", "SELECT id, min(other) = id AS kept FROM reach GROUP BY id")]


@query("near_dedup_comparison", P.statement(_COMPARED, "SELECT 'greedy' AS method, count(*) FILTER (NOT kept) AS dropped FROM verdicts UNION ALL SELECT 'components', count(*) FILTER (NOT kept) FROM least"))
def near_dedup_comparison(spark, sf):
    edges = settle(_edges(spark, sf, "exact"), "edges")
    both = [(name, fn(edges)) for name, fn in (("greedy", greedy.resolve), ("components", greedy.components_keep_first))]
    rows = [v.agg(F.count_if(~F.col("kept")).alias("dropped")).select(F.lit(n).alias("method"), "dropped") for n, v in both]
    return rows[0].union(rows[1])


_SCOPED = [*P.exact("documents", "firsts", "doc_id", f"lang || ':' || {TEXT}"), *[(n, t + " JOIN firsts x ON x.doc_id = a.id JOIN firsts y ON y.doc_id = b.id AND x.lang = y.lang" if n == "cand" else t) for n, t in P.near("firsts", "doc_id", "text")]]


@query("near_dedup_within_language", P.statement([*_SCOPED, *P.edges("exact"), *P.greedy()], "SELECT doc_id FROM firsts WHERE doc_id NOT IN (SELECT id FROM verdicts WHERE NOT kept)"))
def near_dedup_within_language(spark, sf):
    """Exact and near duplicates of one language only: what several languages share stays once in each."""
    docs = load(spark, sf, "documents", ["doc_id", "lang", "text"])
    gone = greedy.resolve(pipeline.near_edges(docs, "doc_id", F.col("text"), CFG, "lang", F.concat_ws(":", "lang", _collapsed()))).filter("NOT kept").select(F.col("id").alias("doc_id"))
    return exact_dedup_within_language(spark, sf).join(gone, "doc_id", "left_anti")


@query("near_cluster_sizes", P.statement([*NEAR, *P.edges("exact"), *P.components()], "SELECT members, count(*) AS clusters FROM (SELECT count(*) AS members FROM verdicts GROUP BY root) GROUP BY members"))
def near_cluster_sizes(spark, sf):
    clusters = greedy.components_keep_first(_edges(spark, sf, "exact")).groupBy("root").agg(F.count(F.lit(1)).alias("members"))
    return clusters.groupBy("members").agg(F.count(F.lit(1)).alias("clusters"))


@query("duplicate_rates", P.statement([*NEAR, *P.edges("exact"), *P.greedy()], """SELECT 'exact' AS phase, (SELECT count(*) FROM documents) AS rows_in, (SELECT count(*) FROM documents) - (SELECT count(*) FROM firsts) AS dropped
UNION ALL SELECT 'near', (SELECT count(*) FROM firsts), (SELECT count(*) FILTER (NOT kept) FROM verdicts)"""))
def duplicate_rates(spark, sf):
    """Rows that reach each phase of the duplicate removal, and rows it drops."""
    before, between = load(spark, sf, "documents", ["doc_id"]).count(), exact_dedup(spark, sf).count()
    gone = greedy.resolve(_edges(spark, sf, "exact"))
    return gone.agg(F.count_if(~F.col("kept")).alias("near")).selectExpr(
        f"stack(2, 'exact', {before}L, {before - between}L, 'near', {between}L, near) as (phase, rows_in, dropped)")


@query("dedup_accuracy", P.statement([*NEAR, *P.edges("exact"), ("flat", "SELECT id, len(tokens) AS n, unnest(tokens) AS token FROM sets"),
       ("truth", "SELECT a.id AS lo, b.id AS hi FROM flat a JOIN flat b ON a.token = b.token AND a.id < b.id AND 100 * least(a.n, b.n) >= 80 * greatest(a.n, b.n) GROUP BY a.id, b.id HAVING 100 * count(*) >= 80 * (any_value(a.n) + any_value(b.n) - count(*))")],
       "SELECT (SELECT count(*) FROM edges JOIN truth USING (lo, hi)) / (SELECT count(*) FROM truth) AS recall, (SELECT count(*) FROM edges JOIN truth USING (lo, hi)) / (SELECT count(*) FROM edges) AS \"precision\""))
def dedup_accuracy(spark, sf):
    """The token sets are the only wide table: first rows are found by digests, and no text is moved.

    The candidates of both ways are verified together (tau_lsh and 80 percent decide alike), so token sets move once.
    """
    docs = load(spark, sf, "documents", ["doc_id", "text"])
    sets = settle(docs.select("doc_id", dedup.token_set(F.col("text")).alias("tokens")), "sets")
    marked = docs.select("doc_id", dedup.digest(_collapsed()).alias("digest"))
    firsts = settle(dedup.exact(marked, F.col("digest"), ["doc_id"]).select("doc_id"), "firsts")
    banded, met = pipeline.set_candidates(sets, "doc_id", CFG, firsts), dedup.prefix_pairs(sets, "doc_id", 80, firsts)
    pairs = settle(banded.union(met).distinct(), "candidates")
    similar = settle(dedup.verify_grouped(pairs, sets, "doc_id", "common", 80).select("lo", "hi"), "similar")
    return analysis.edge_accuracy(*(similar.join(found.hint("merge"), ["lo", "hi"], "left_semi") for found in (banded, met)))


@query("minhash_ml_crosscheck")
def minhash_ml_crosscheck(spark, sf):
    from paircuration.operators.ml_crosscheck import ml_crosscheck

    return ml_crosscheck(_sets(spark, sf), "doc_id", 0.2)


# ---- stage 4 --------------------------------------------------------------------------------------------------------

_DETECT = "pair_id, phrase_hits, has_structure, section_count, generic_hits, ai_matched, cast(ai_tenths / 10.0 AS DECIMAL(3,1)) AS ai_score"
for _name, _cfg in {"detector_scores": DetectorConfig(), "detector_per_match": DetectorConfig(count="per_match")}.items():
    query(_name, P.statement([*P.functions(), *P.detected(_cfg)], f"SELECT {_DETECT} FROM detected"))(
        lambda spark, sf, cfg=_cfg: detector.score(_functions(spark, sf), cfg).select("pair_id", F.col("phrase_hits").cast("bigint").alias("phrase_hits"), "has_structure", "section_count", F.col("generic_hits").cast("bigint").alias("generic_hits"), "ai_matched", "ai_score"))


@query("detector_flags", P.statement([*P.functions(), *P.detected()], "SELECT pair_id, ai_matched FROM detected WHERE ai_flag"))
def detector_flags(spark, sf):
    return detector.score(_functions(spark, sf)).filter("ai_flag").select("pair_id", "ai_matched")


@query("detector_drop_policy", P.statement([*P.functions(), *P.detected()], "SELECT pair_id FROM detected WHERE NOT ai_flag"))
def detector_drop_policy(spark, sf):
    cfg = DetectorConfig(policy="drop")
    return detector.policy(detector.score(_functions(spark, sf), cfg), cfg).select("pair_id")


@query("detector_sweep", P.statement([*P.functions(), *P.detected()], "SELECT threshold, count(*) FILTER (ai_tenths >= threshold) AS kept FROM detected, (SELECT cast(unnest(range(1, 11)) AS DOUBLE) AS threshold) GROUP BY threshold"))
def detector_sweep(spark, sf):
    return analysis.sweep(detector.score(_functions(spark, sf)), "ai_tenths", [float(i) for i in range(1, 11)])


@query("detector_by_language", P.statement([*P.functions(), *P.detected()], "SELECT language, count(*) AS n, avg(CASE WHEN ai_flag THEN 1.0 ELSE 0.0 END) AS flag_rate FROM detected GROUP BY language"))
def detector_by_language(spark, sf):
    return detector.score(_functions(spark, sf)).groupBy("language").agg(F.count(F.lit(1)).alias("n"), F.avg(F.col("ai_flag").cast("double")).alias("flag_rate"))


_HABIT = """SELECT pair_id, coalesce(habit, false) AS repeated_structure FROM ordered LEFT JOIN
(SELECT repo, section_order, true AS habit FROM (SELECT *, sum(n) OVER (PARTITION BY repo) AS total FROM (SELECT repo, section_order, count(*) AS n FROM ordered GROUP BY ALL)) WHERE n >= 0.5 * total AND n >= 5 AND section_order <> '') h USING (repo, section_order)"""
_HEADS = ", ".join(f"CASE WHEN instr(doc, '{h}') > 0 THEN '{i}' END" for i, h in enumerate(("Parameters:", "Returns:", "Raises:", "Examples:")))


@query("detector_repeated_structure", P.statement([*P.functions(), ("ordered", f"SELECT pair_id, repo, concat_ws('>', {_HEADS}) AS section_order FROM fp")], _HABIT))
def detector_repeated_structure(spark, sf):
    return detector.repeated_structure(_functions(spark, sf)).select("pair_id", "repeated_structure")


@query("detector_truth", P.statement([("fp", carriers.function_sql(DUCK)), *P.detected()], """SELECT 'phrase' AS signal, count(*) FILTER (phrase_hits > 0 AND is_phrase) AS hit, count(*) FILTER (phrase_hits > 0) AS found, count(*) FILTER (is_phrase) AS planted FROM detected
UNION ALL SELECT 'generic', count(*) FILTER (generic_hits > 0 AND is_generic), count(*) FILTER (generic_hits > 0), count(*) FILTER (is_generic) FROM detected
UNION ALL SELECT 'structure', count(*) FILTER (has_structure AND is_bullets), count(*) FILTER (has_structure), count(*) FILTER (is_bullets) FROM detected"""))
def detector_truth(spark, sf):
    from paircuration.functions.dialect import SPARK
    from paircuration.sources.tables import run_sql

    found = detector.score(run_sql(spark, carriers.function_sql(SPARK, "@docs@"), docs=load(spark, sf, "documents")))
    rows = found.agg(*[x for name, a, b in (("phrase", "phrase_hits > 0", "is_phrase"), ("generic", "generic_hits > 0", "is_generic"), ("structure", "has_structure", "is_bullets"))
                       for x in (F.expr(f"count_if({a} AND {b})").alias(f"{name}_hit"), F.expr(f"count_if({a})").alias(f"{name}_found"), F.expr(f"count_if({b})").alias(f"{name}_planted"))])
    return rows.selectExpr("stack(3, 'phrase', phrase_hit, phrase_found, phrase_planted, 'generic', generic_hit, generic_found, generic_planted, 'structure', structure_hit, structure_found, structure_planted) as (signal, hit, found, planted)")


# ---- whole pipeline and analysis ------------------------------------------------------------------------------------

def _curated(spark, sf):
    return pipeline.run(_functions(spark, sf))


def _final(spark, sf):
    return settle(_curated(spark, sf).final, "final")


CURATED = P.curated()


@query("curated_pairs", P.statement(CURATED, "SELECT pair_id, language, quality, ai_flag, ai_matched FROM cur"))
def curated_pairs(spark, sf):
    return _curated(spark, sf).final.select("pair_id", "language", "quality", "ai_flag", "ai_matched")


_COUNTS = " UNION ALL ".join(f"SELECT {i} AS step, '{s}' AS stage, (SELECT count(*) FROM {t}) AS kept" for i, (s, t) in enumerate(
    (("candidates", "fp"), ("stage1", "stage1"), ("stage2", "retained"), ("exact", "firsts"), ("near", "deduped"), ("final", "cur"))))


@query("funnel", P.statement(CURATED, f"SELECT *, kept / max(kept) OVER () AS retention FROM ({_COUNTS})"))
def funnel(spark, sf):
    return pipeline.funnel(_functions(spark, sf), _curated(spark, sf))


@query("corpus_summary", P.statement(CURATED, """SELECT count(*) AS pairs, round(avg(quality), 6) AS quality_mean, round(median(quality), 6) AS quality_median, round(stddev_samp(quality), 6) AS quality_sd, min(quality) AS quality_min, max(quality) AS quality_max,
round(avg(complexity), 6) AS complexity_mean, median(complexity)::DOUBLE AS complexity_median, count(*) FILTER (typed_slots > 0) AS typed, count(*) FILTER (ai_flag) AS flagged FROM cur"""))
def corpus_summary(spark, sf):
    out = analysis.summary(_final(spark, sf))
    return out.select(*[F.round(c, 6).alias(c) if c in ("quality_mean", "quality_median", "quality_sd", "complexity_mean") else F.col(c) for c in out.columns])


@query("corpus_summary_sketch")
def corpus_summary_sketch(spark, sf):
    return analysis.summary(_final(spark, sf), exact=False)


@query("language_shares", P.statement(P.functions(), "SELECT language, count(*) AS n, count(*) / sum(count(*)) OVER () AS share FROM fp GROUP BY language"))
def language_shares(spark, sf):
    return analysis.shares(_functions(spark, sf), "language")


@query("text_language_shares", "SELECT lang, count(*) AS n, count(*) / sum(count(*)) OVER () AS share FROM documents GROUP BY lang")
def text_language_shares(spark, sf):
    return analysis.shares(load(spark, sf, "documents", ["lang"]), "lang")


@query("quality_by_language", P.statement(_SCORED, "SELECT language, count(*) AS n, round(avg(quality), 6) AS mean, round(quantile_cont(quality, 0.25), 6) AS q1, round(quantile_cont(quality, 0.5), 6) AS median, round(quantile_cont(quality, 0.75), 6) AS q3 FROM scored GROUP BY language"))
def quality_by_language(spark, sf):
    out = analysis.quartiles(_scored(spark, sf), "language", "quality")
    return out.select("language", "n", *[F.round(c, 6).alias(c) for c in ("mean", "q1", "median", "q3")])


@query("quality_histogram", P.statement(_SCORED, "SELECT cast(floor(quality / 0.5) * 0.5 AS DOUBLE) AS low, count(*) AS n FROM scored GROUP BY 1"))
def quality_histogram(spark, sf):
    return analysis.histogram(_scored(spark, sf), "quality", 0.5)


@query("complexity_distribution", P.statement(P.functions(), "SELECT complexity, count(*) AS n FROM fp GROUP BY complexity"))
def complexity_distribution(spark, sf):
    return _functions(spark, sf).groupBy("complexity").agg(F.count(F.lit(1)).alias("n"))


@query("typed_by_language", P.statement(P.functions(), "SELECT language, avg(CASE WHEN typed_slots > 0 THEN 1.0 ELSE 0.0 END) AS typed_rate FROM fp GROUP BY language"))
def typed_by_language(spark, sf):
    return _functions(spark, sf).groupBy("language").agg(F.avg((F.col("typed_slots") > 0).cast("double")).alias("typed_rate"))


@query("examples_rate", P.statement([*P.functions(), *P.stage1()], f"SELECT (SELECT avg(CASE WHEN {R.section(DUCK, 'examples')} THEN 1.0 ELSE 0.0 END) FROM fp) AS before_filter, (SELECT coalesce(sum(CASE WHEN {R.section(DUCK, 'examples')} THEN 1 ELSE 0 END), 0)::BIGINT FROM stage1) AS after_filter"))
def examples_rate(spark, sf):
    from paircuration.functions.dialect import SPARK

    has = F.expr(R.section(SPARK, "examples"))
    pairs = _functions(spark, sf).withColumn("has", has)
    failing = F.array(*[F.lit(False)])
    for fail in stage1.rules().values():
        failing = F.concat(failing, F.array(fail))
    kept = ~F.array_contains(failing, True)
    return pairs.agg(F.avg(F.col("has").cast("double")).alias("before_filter"), F.count_if(kept & F.col("has")).alias("after_filter"))


@query("repo_coverage", "SELECT *, row_number() OVER (ORDER BY n DESC, source) AS place, sum(n) OVER (ORDER BY n DESC, source ROWS UNBOUNDED PRECEDING) / sum(n) OVER () AS cumulative FROM (SELECT source, count(*) AS n FROM documents GROUP BY source)")
def repo_coverage(spark, sf):
    return analysis.coverage(load(spark, sf, "documents", ["source"]), "source")


@query("supplier_coverage", "SELECT *, row_number() OVER (ORDER BY n DESC, l_suppkey) AS place, sum(n) OVER (ORDER BY n DESC, l_suppkey ROWS UNBOUNDED PRECEDING) / sum(n) OVER () AS cumulative FROM (SELECT l_suppkey, count(*) AS n FROM lineitem GROUP BY l_suppkey)")
def supplier_coverage(spark, sf):
    return analysis.coverage(load(spark, sf, "lineitem", ["l_suppkey"]), "l_suppkey")


@query("repo_gini", "SELECT round(2 * sum(i * n) / (count(*) * sum(n)) - (count(*) + 1) / count(*), 9) AS gini FROM (SELECT n, row_number() OVER (ORDER BY n, l_suppkey) AS i FROM (SELECT l_suppkey, count(*) AS n FROM lineitem GROUP BY l_suppkey))")
def repo_gini(spark, sf):
    return analysis.gini(load(spark, sf, "lineitem", ["l_suppkey"]), "l_suppkey").select(F.round("gini", 9).alias("gini"))


@query("language_repo_cube", "SELECT lang, source, count(*) AS n FROM documents GROUP BY CUBE (lang, source)")
def language_repo_cube(spark, sf):
    return load(spark, sf, "documents", ["lang", "source"]).cube("lang", "source").agg(F.count(F.lit(1)).alias("n"))


@query("repo_selection", "SELECT doc_id FROM documents WHERE source IN (SELECT source FROM (SELECT source, count(*) AS n, avg(CASE WHEN length(trim(text)) > 0 THEN 1.0 ELSE 0.0 END) AS rate FROM documents GROUP BY source) WHERE n >= (SELECT count(*) / 40 FROM documents) AND rate >= 0.5)")
def repo_selection(spark, sf):
    docs = load(spark, sf, "documents", ["doc_id", "source", "text"])
    least = -(-docs.count() // 40)
    return extract.select_repos(docs, "source", least, 0.5, doc="text").select("doc_id")


@query("repo_selection_per_domain", """WITH st AS (SELECT source, min(lang) AS domain, count(*) AS n FROM documents GROUP BY source),
pick AS (SELECT source FROM (SELECT *, row_number() OVER (PARTITION BY domain ORDER BY n DESC, source) AS place FROM st) WHERE place <= 3)
SELECT source, count(*) AS n FROM documents WHERE source IN (SELECT source FROM pick) GROUP BY source""")
def repo_selection_per_domain(spark, sf):
    return extract.select_repos(load(spark, sf, "documents", ["doc_id", "source", "lang", "text"]), "source", domain="lang", per_domain=3, doc="text").groupBy("source").agg(F.count(F.lit(1)).alias("n"))


@query("temporal_cutoff", "SELECT event_id FROM events WHERE ts < (SELECT min(ts) + INTERVAL 7 DAY FROM events)")
def temporal_cutoff(spark, sf):
    events = load(spark, sf, "events", ["event_id", "ts"])
    limit = events.agg((F.min("ts") + F.expr("interval 7 days")).alias("t")).first()["t"]
    return extract.temporal_cutoff(events, "ts", limit.isoformat(sep=" ")).select("event_id")


# ---- split, packing, plan -------------------------------------------------------------------------------------------

_SPLIT = """SELECT pair_id, language, CASE WHEN r <= floor(total * '0.8'::DOUBLE) THEN 'train' WHEN r <= floor(total * '0.9'::DOUBLE) THEN 'validation' ELSE 'test' END AS split
FROM (SELECT pair_id, language, row_number() OVER (PARTITION BY language ORDER BY md5('3407:' || pair_id), pair_id) AS r, count(*) OVER (PARTITION BY language) AS total FROM fp)"""


@query("split_rows", P.statement(P.functions(), _SPLIT))
def split_rows(spark, sf):
    return split.stratified(_functions(spark, sf).select("pair_id", "language"), "language", "pair_id").select("pair_id", "language", "split")


@query("split_counts", P.statement(P.functions(), f"SELECT language, split, count(*) AS n FROM ({_SPLIT}) GROUP BY language, split"))
def split_counts(spark, sf):
    return split_rows(spark, sf).groupBy("language", "split").agg(F.count(F.lit(1)).alias("n"))


_HASHED = "CASE WHEN b < 800 THEN 'train' WHEN b < 900 THEN 'validation' ELSE 'test' END"


@query("split_hashed", f"SELECT doc_id, {_HASHED} AS split FROM (SELECT doc_id, cast('0x' || substr(md5('3407:' || doc_id), 1, 8) AS BIGINT) % 1000 AS b FROM documents)")
def split_hashed(spark, sf):
    return split.hashed(load(spark, sf, "documents", ["doc_id"]), "doc_id")


@query("split_leakage_safe", P.statement([*NEAR, *P.edges("exact"), *P.components()],
       f"SELECT doc_id, {_HASHED} AS split FROM (SELECT doc_id, cast('0x' || substr(md5('3407:' || coalesce(root, doc_id)), 1, 8) AS BIGINT) % 1000 AS b FROM firsts LEFT JOIN verdicts ON id = doc_id)"))
def split_leakage_safe(spark, sf):
    return split.leakage_safe(exact_dedup(spark, sf), greedy.components_keep_first(_edges(spark, sf, "exact")), "doc_id")


@query("truncated_tokens", "SELECT doc_id, least(2048, len(string_split(trim(regexp_replace(text, '[ \\t\\n\\r\\f\\v]+', ' ', 'g')), ' '))) AS n FROM documents")
def truncated_tokens(spark, sf):
    return load(spark, sf, "documents", ["doc_id", "text"]).select("doc_id", F.size(split.truncate(F.col("text"))).cast("bigint").alias("n"))


_COUNT_TOKENS = "len(regexp_extract_all(text, '[^ \\t\\n\\r]+'))"


@query("packed_sequences", f"SELECT doc_id, source, n, run - n AS begin, floor((run - n) / 2048)::BIGINT AS chunk, (run - n) % 2048 AS \"offset\" FROM (SELECT *, sum(n) OVER (PARTITION BY source ORDER BY doc_id)::BIGINT AS run FROM (SELECT doc_id, source, {_COUNT_TOKENS} AS n FROM documents))")
def packed_sequences(spark, sf):
    docs = load(spark, sf, "documents", ["doc_id", "source", "text"]).select("doc_id", "source", F.regexp_count("text", F.lit("[^ \t\n\r]+")).cast("bigint").alias("n"))
    return split.running_pack(docs, "source", "doc_id", "n", 2048)


for _method in ("next_fit", "first_fit_decreasing"):
    query(f"packed_{_method}")(lambda spark, sf, m=_method: split.pack(load(spark, sf, "documents", ["doc_id", "text"]).select("doc_id", F.regexp_count("text", F.lit("[^ \t\n\r]+")).alias("n")), "doc_id", "n", 2048, m))


@query("step_plan", """WITH t AS (SELECT ceil(count(*) / 8)::BIGINT AS per FROM documents)
SELECT s AS step, (floor((s - 1) / per) + 1)::BIGINT AS epoch, round(CASE WHEN s <= 50 THEN s / 50 ELSE (3 * per - s) / greatest(1, 3 * per - 50) END * 1e-4, 12) AS rate FROM t, (SELECT unnest(range(1, 3 * per + 1)) AS s FROM t)""")
def step_plan(spark, sf):
    return split.step_plan(spark, load(spark, sf, "documents", ["doc_id"]).count())


# ---- metrics and baselines ------------------------------------------------------------------------------------------

def _replies(spark, sf):
    pairs = carriers.reply_pairs(spark, sf)
    return pairs.select(F.concat_ws("-", "conv_id", "turn").alias("pair"), metrics.tokens(F.col("candidate")).alias("cand"), metrics.tokens(F.col("reference")).alias("ref"))


def _bleu_parts(max_n=4, source: str | None = None) -> P.Parts:
    """`source` is a SELECT of (pair, candidate, reference)."""
    source = source or f"SELECT conv_id || '-' || turn AS pair, candidate, reference FROM ({carriers.reply_sql()})"
    tok = "list_filter(string_split_regex(lower({0}), '[ \\n\\t]+'), lambda t: t <> '')"
    grams = " UNION ALL ".join(
        f"SELECT pair, {n} AS n, array_to_string({{0}}[i : i + {n - 1}], ' ') AS gram FROM (SELECT pair, {{0}}, unnest(range(1, len({{0}}) - {n} + 2)) AS i FROM tok)" for n in range(1, max_n + 1))
    return [
        ("tok", f"SELECT pair, {tok.format('candidate')} AS cand, {tok.format('reference')} AS ref FROM ({source})"),
        ("cg", f"SELECT pair, n, gram, count(*) AS times FROM ({grams.format('cand')}) GROUP BY ALL"), ("rg", f"SELECT pair, n, gram, count(*) AS times FROM ({grams.format('ref')}) GROUP BY ALL"),
        ("clip", "SELECT c.pair, c.n, sum(least(c.times, coalesce(r.times, 0))) AS m, sum(c.times) AS t FROM cg c LEFT JOIN rg r USING (pair, n, gram) GROUP BY c.pair, c.n"),
    ]


def _bleu_select(smooth: str, digits: int = 6) -> str:
    m, t = "coalesce(m, 0)", "coalesce(t, 0)"
    if smooth == "add1":
        m, t = f"{m} + CASE WHEN o.n > 1 THEN 1 ELSE 0 END", f"{t} + CASE WHEN o.n > 1 THEN 1 ELSE 0 END"
    if smooth == "eps":
        m = f"CASE WHEN {m} = 0 THEN 0.1 ELSE {m} END"
    return f"""SELECT pair, round(CASE WHEN min(ok) = 0 THEN 0.0 ELSE any_value(bp) * exp(avg(l)) END, {digits}) AS bleu FROM (
SELECT tok.pair, CASE WHEN len(cand) >= len(ref) THEN 1.0 WHEN len(cand) = 0 THEN 0.0 ELSE exp(1 - len(ref) / len(cand)) END AS bp, CASE WHEN ({m}) > 0 AND ({t}) > 0 THEN 1 ELSE 0 END AS ok,
CASE WHEN ({m}) > 0 AND ({t}) > 0 THEN ln(({m})::DOUBLE / ({t})) END AS l FROM tok JOIN (SELECT unnest(range(1, 5)) AS n) o ON true LEFT JOIN clip ON clip.pair = tok.pair AND clip.n = o.n) GROUP BY pair"""


for _smooth, _name in (("none", "bleu_sentence"), ("add1", "bleu_sentence_add1"), ("eps", "bleu_sentence_eps")):
    query(_name, P.statement(_bleu_parts(), _bleu_select(_smooth)))(lambda spark, sf, s=_smooth: metrics.bleu(_replies(spark, sf), "pair", smooth=s).select("pair", F.round("bleu", 6).alias("bleu")))


@query("bleu_corpus", P.statement(_bleu_parts(), "SELECT round(CASE WHEN c >= r THEN 1 ELSE exp(1 - r / c) END * exp(l), 9) AS bleu FROM (SELECT avg(ln(m / t)) AS l FROM (SELECT n, sum(m) AS m, sum(t) AS t FROM clip GROUP BY n)), (SELECT sum(len(cand)) AS c, sum(len(ref)) AS r FROM tok)"))
def bleu_corpus(spark, sf):
    return metrics.bleu_corpus(_replies(spark, sf), "pair").select(F.round("bleu", 9).alias("bleu"))


def _lcs_parts() -> P.Parts:
    """One table row per candidate token: cells that match grow from the diagonal, then a running maximum."""
    cells = "list_transform(range(1, len(ref) + 1), lambda k: CASE WHEN cand[i + 1] <> ref[k] THEN line[k] WHEN k = 1 THEN 1 ELSE line[k - 1] + 1 END)"
    return [
        ("folded", f"SELECT pair, cand, ref, 0 AS i, list_transform(ref, lambda t: 0) AS line FROM tok UNION ALL SELECT pair, cand, ref, i + 1, list_transform(range(1, len(ref) + 1), lambda k: list_max(cells[1:k])) FROM (SELECT *, {cells} AS cells FROM folded WHERE i < len(cand))"),
        ("ends", "SELECT pair, coalesce(line[len(ref)], 0)::INT AS lcs, len(cand) AS c, len(ref) AS r FROM folded WHERE i = len(cand)"),
        ("shares", "SELECT pair, lcs, CASE WHEN c > 0 THEN lcs / c ELSE 0.0::DOUBLE END AS p, CASE WHEN r > 0 THEN lcs / r ELSE 0.0::DOUBLE END AS q FROM ends"),
        ("overlap", "SELECT *, CASE WHEN lcs > 0 THEN 2.0 * p * q / (q + p) ELSE 0.0::DOUBLE END AS lcs_f FROM shares"),
    ]


@query("lcs_overlap", P.statement([*_bleu_parts()[:1], *_lcs_parts()], 'SELECT pair, lcs, p AS "precision", q AS recall, lcs_f FROM overlap'))
def lcs_overlap(spark, sf):
    return metrics.lcs_overlap(_replies(spark, sf)).select("pair", "lcs", "precision", "recall", "lcs_f")


def _measured(generated: DataFrame) -> DataFrame:
    pairs = generated.select("pair_id", "language", metrics.tokens(F.col("generated")).alias("cand"), metrics.tokens(F.col("doc")).alias("ref"))
    return metrics.lcs_overlap(pairs).join(metrics.bleu(pairs, "pair_id", smooth="add1"), "pair_id").select("pair_id", "language", "bleu", "lcs_f")


def _scored_sql(pools: str, kinds: str) -> P.Parts:
    """scores(kind, language, bleu, lcs_f) of generated texts; `kinds` is a SELECT of (kind, pair_id, language, generated, doc) from gen."""
    return [*P.curated(), ("parts", P.SPLIT), ("test", "SELECT * FROM parts WHERE split = 'test'"), *P.retrieval(pools), ("made", kinds),
            *_bleu_parts(source="SELECT kind || '#' || pair_id AS pair, generated AS candidate, doc AS reference FROM made"), ("bleus", _bleu_select("add1", 15)), *_lcs_parts(),
            ("scores", "SELECT kind, language, bleu, lcs_f FROM made JOIN bleus b ON b.pair = kind || '#' || pair_id JOIN overlap o ON o.pair = b.pair")]


_KINDS = "SELECT 'old' AS kind, pair_id, language, template AS generated, doc FROM gen UNION ALL SELECT 'new', pair_id, language, coalesce(found, template), doc FROM gen"
_REPORT = """SELECT l.language, n, round(bo, 6) AS bleu_untrained, round(lo, 6) AS lcs_untrained, round(bn, 6) AS bleu_retrieved, round(ln, 6) AS lcs_retrieved,
CASE WHEN bo <> 0 THEN round((bn - bo) / bo, 6) END AS bleu_gain, CASE WHEN lo <> 0 THEN round((ln - lo) / lo, 6) END AS lcs_gain FROM wide l"""
_STRATA = [("strata", "SELECT kind, language, count(*) AS n, avg(bleu) AS b, avg(lcs_f) AS l FROM scores GROUP BY kind, language"),
           ("means", "SELECT * FROM strata UNION ALL SELECT kind, '(macro)', sum(n)::BIGINT, avg(b), avg(l) FROM strata GROUP BY kind UNION ALL SELECT kind, '(micro)', count(*), avg(bleu), avg(lcs_f) FROM scores GROUP BY kind"),
           ("wide", "SELECT o.language, o.n, o.b AS bo, o.l AS lo, w.b AS bn, w.l AS ln FROM means o JOIN means w ON o.kind = 'old' AND w.kind = 'new' AND o.language = w.language")]


@query("baseline_comparison", P.statement([*_scored_sql("SELECT 'train' AS pool, pair_id, doc, code FROM parts WHERE split = 'train'", _KINDS), *_STRATA], _REPORT))
def baseline_comparison(spark, sf):
    """Untrained template against retrieval from the curated training split, with relative gains: per language, macro and micro."""
    parts = settle(split.stratified(_final(spark, sf), "language", "pair_id"), "split")
    train, test = parts.filter("split = 'train'"), parts.filter("split = 'test'")
    old = metrics.report(settle(_measured(generators.untrained(test)), "scores"), "language", ["bleu", "lcs_f"])
    new = metrics.report(settle(_measured(settle(generators.retrieve(train, test), "generated")), "scores"), "language", ["bleu", "lcs_f"]).drop("n")
    joined = old.withColumnsRenamed({"bleu": "bleu_untrained", "lcs_f": "lcs_untrained"}).join(new.withColumnsRenamed({"bleu": "bleu_retrieved", "lcs_f": "lcs_retrieved"}), "language")
    joined = joined.withColumn("bleu_gain", metrics.relative_gain(F.col("bleu_untrained"), F.col("bleu_retrieved"))).withColumn("lcs_gain", metrics.relative_gain(F.col("lcs_untrained"), F.col("lcs_retrieved")))
    return joined.select("language", "n", *[F.round(c, 6).alias(c) for c in joined.columns if c not in ("language", "n")])


_POOLS = """SELECT pool, pair_id, doc, code FROM (SELECT 'curated' AS pool, pair_id, doc, code FROM cur UNION ALL SELECT 'uncurated', pair_id, doc, code FROM fp
UNION ALL SELECT 'uncurated_sample', pair_id, doc, code FROM (SELECT *, row_number() OVER (ORDER BY md5(pair_id::VARCHAR)) AS place FROM fp) WHERE place <= (SELECT count(*) FROM cur)) WHERE pair_id NOT IN (SELECT pair_id FROM test)"""


@query("curation_ablation", P.statement(_scored_sql(_POOLS, "SELECT pool AS kind, pair_id, language, coalesce(found, template) AS generated, doc FROM gen"),
       "SELECT kind AS pool, count(*) AS n, round(avg(bleu), 6) AS bleu, round(avg(lcs_f), 6) AS lcs_f FROM scores GROUP BY kind"))
def curation_ablation(spark, sf):
    """Retrieval from the curated pool, from everything, and from a sample of everything of the curated pool's size."""
    everything = settle(_functions(spark, sf).select("pair_id", "doc", "code"), "everything")  # rendered once
    curated = _final(spark, sf)
    test = settle(split.stratified(curated, "language", "pair_id").filter("split = 'test'"), "test")
    sample = split.first_rows(everything, F.md5(F.col("pair_id").cast("string")), curated.count())  # the sample is the feature
    out = None
    for name, pool in {"curated": curated, "uncurated": everything, "uncurated_sample": sample}.items():
        train = pool.select("pair_id", "doc", "code").join(test.select("pair_id"), "pair_id", "left_anti")
        scores = settle(_measured(settle(generators.retrieve(train, test), "generated")), "scores")
        row = scores.agg(F.lit(name).alias("pool"), F.count(F.lit(1)).alias("n"), F.round(F.avg("bleu"), 6).alias("bleu"), F.round(F.avg("lcs_f"), 6).alias("lcs_f"))
        out = row if out is None else out.union(row)
    return out


_SKIPS = ("", "stage1", "stage2", "exact", "near", "detector")
_LEFT_OUT = " UNION ALL ".join(f"SELECT '{k or 'nothing'}' AS left_out, * FROM ({P.statement(P.curated(k), 'SELECT count(*) AS kept, round(avg(quality), 6) AS quality_mean FROM cur')}) s{i}" for i, k in enumerate(_SKIPS))


@query("stage_ablation", _LEFT_OUT)
def stage_ablation(spark, sf):
    """Kept pairs and their mean score with each stage left out in turn."""
    out = None
    for k in _SKIPS:
        kept = pipeline.run(_functions(spark, sf), skip=frozenset([k] if k else [])).final
        row = kept.agg(F.lit(k or "nothing").alias("left_out"), F.count(F.lit(1)).alias("kept"), F.round(F.avg("quality"), 6).alias("quality_mean"))
        out = row if out is None else out.union(row)
    return out


# ---- extraction and leakage -----------------------------------------------------------------------------------------

def _files(spark, sf):
    from paircuration.functions.dialect import SPARK
    from paircuration.sources.tables import run_sql

    return run_sql(spark, carriers.source_sql(SPARK, "@pairs@"), pairs=_functions(spark, sf))


_FILES = [*P.functions(), ("files", carriers.source_sql(DUCK, "fp"))]


@query("source_files", P.statement(_FILES, "SELECT path, language, md5(source) AS digest, licence, idle_days FROM files"))
def source_files(spark, sf):
    return _files(spark, sf).select("path", "language", F.md5("source").alias("digest"), "licence", "idle_days")


@query("function_extract", P.statement(_FILES, "SELECT path, language, name, params, kind AS return_type, doc, complexity FROM files"))
def function_extract(spark, sf):
    """Functions of all five languages, read back from rendered files: python by its syntax tree, the others by a lexical scan."""
    found = extract.extract_functions(_files(spark, sf).select("path", "source", "language"))
    return found.select("path", "language", "name", F.array_join("params.name", ",").alias("params"), "return_type", F.trim("doc").alias("doc"), "complexity")


@query("function_signatures", P.statement(_FILES, "SELECT language, count(*) AS functions, sum(CASE WHEN params = '' THEN 0 ELSE len(string_split(params, ',')) END)::BIGINT AS params, count(kind) AS returns, count(doc) AS documented FROM files GROUP BY language"))
def function_signatures(spark, sf):
    found = extract.extract_functions(_files(spark, sf).select("path", "source", "language"))
    return found.groupBy("language").agg(F.count(F.lit(1)).alias("functions"), F.sum(F.size("params")).alias("params"), F.count("return_type").alias("returns"), F.count("doc").alias("documented"))


_CHOSEN = "SELECT path FROM files WHERE repo IN (SELECT repo FROM files GROUP BY repo HAVING min(licence) IN ('mit', 'apache-2.0', 'gpl-3.0') AND min(idle_days) <= 600 AND count(*) >= 5)"


@query("doc_discovery", P.statement(_FILES, "SELECT path, doc FROM files"))
def doc_discovery(spark, sf):
    """Docstring of python files, block comment at the head of the others."""
    return _files(spark, sf).select("path", extract.doc_of(F.col("source"), F.col("language")).alias("doc"))


@query("header_signatures", P.statement(_FILES, "SELECT path, params, CASE WHEN language = 'typescript' OR (language = 'python' AND instr(source, ': int') > 0) THEN CASE WHEN params = '' THEN 0 ELSE len(string_split(params, ',')) END ELSE 0 END::INT AS typed FROM files WHERE language IN ('python', 'javascript', 'typescript')"))
def header_signatures(spark, sf):
    found = _files(spark, sf).filter("language IN ('python', 'javascript', 'typescript')").select("path", extract.signature(F.col("source")).alias("s"))
    return found.select("path", F.array_join("s.name", ",").alias("params"), F.size(F.filter("s", lambda x: x["type"].isNotNull())).alias("typed"))


@query("source_pairs", P.statement(_FILES, """SELECT path || ':' || (CASE WHEN language <> 'python' AND doc IS NOT NULL THEN 2 ELSE 1 END) AS pair_id, repo, licence, url, '1.0' AS version, complexity,
CASE WHEN language IN ('java', 'cpp', 'typescript') OR (language = 'python' AND instr(source, ': int') > 0) THEN CASE WHEN params = '' THEN 0 ELSE len(string_split(params, ',')) END ELSE 0 END + CASE WHEN kind IS NOT NULL THEN 1 ELSE 0 END AS typed_slots FROM files"""))
def source_pairs(spark, sf):
    """Pair rows with their versioned origin, as the stages take them."""
    files = _files(spark, sf)
    rows = extract.pairs(extract.extract_functions(files.select("path", "source", "language")), files, "1.0")
    return rows.select("pair_id", "meta.repo", "meta.licence", "meta.url", "meta.version", "complexity", F.col("typed_slots").alias("typed_slots"))


@query("repo_selection_licence_activity", P.statement(_FILES, _CHOSEN))
def repo_selection_licence_activity(spark, sf):
    return extract.select_repos(_files(spark, sf), min_rows=5, licences=list(carriers.LICENCES[:3]), max_idle_days=600, doc="source").select("path")


@query("source_curation")
def source_curation(spark, sf):
    """The whole plan from source files to split pairs with their versioned origin."""
    done = pipeline.from_files(_files(spark, sf).select("path", "repo", "language", "source", "licence", "idle_days", "url"), "1.0", licences=list(carriers.LICENCES[:3]), max_idle_days=600, min_rows=5)
    final = split.stratified(settle(done.final, "final"), "language", "pair_id")
    return final.select("pair_id", "language", "quality", "ai_score", "ai_flag", "split", "meta")


@query("cyclomatic_proxy", P.statement(P.functions(), "SELECT pair_id, (1 + len(regexp_extract_all(regexp_replace(code, '(//|#)[^\\n]*', ' ', 'g'), '\\b(if|elif|for|while|case|catch|except)\\b')))::INT AS proxy FROM fp"))
def cyclomatic_proxy(spark, sf):
    return _functions(spark, sf).select("pair_id", extract.cyclomatic_proxy(F.col("code")).cast("int").alias("proxy"))


_WORDS8 = "SELECT DISTINCT {id}, array_to_string(w[i : i + 7], ' ') AS gram FROM (SELECT {id}, w, unnest(range(1, greatest(len(w) - 6, 2))) AS i FROM (SELECT {id}, regexp_extract_all(lower(text), '[a-z0-9_]+') AS w FROM {t}) WHERE len(w) > 0)"


@query("benchmark_overlap", f"WITH d AS ({_WORDS8.format(id='doc_id', t='documents')}), b AS ({_WORDS8.format(id='item_id', t='benchmark')}) SELECT doc_id, item_id, count(*) AS shared FROM d JOIN b USING (gram) GROUP BY doc_id, item_id")
def benchmark_overlap(spark, sf):
    """Distinct shared eight-word passages (a text of fewer words is one passage); each side is reduced to distinct ones before the join."""
    def grams(table, key):
        w = load(spark, sf, table).select(key, F.regexp_extract_all(F.lower("text"), F.lit("[a-z0-9_]+"), F.lit(0)).alias("w")).filter(F.size("w") > 0)
        return w.select(key, F.explode(F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(F.size("w") - 7, F.lit(1))), lambda i: F.array_join(F.slice("w", i, 8), " ")))).alias("gram"))
    return grams("documents", "doc_id").join(grams("benchmark", "item_id"), "gram").groupBy("doc_id", "item_id").agg(F.count(F.lit(1)).alias("shared"))


@query("embedding_neighbours")
def embedding_neighbours(spark, sf):
    from paircuration.operators.cosine import neighbours

    return neighbours(load(spark, sf, "embeddings"), "vec_id", "embedding", 0.6)
