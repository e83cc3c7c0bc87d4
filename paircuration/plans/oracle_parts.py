"""Common table expressions of the deduplication and curation chain, for the SQL engine that checks the queries."""

from __future__ import annotations

from paircuration import carriers
from paircuration.config import DIMENSIONS, DedupConfig, DetectorConfig, Stage1Config, Stage2Config
from paircuration.functions import rules as R
from paircuration.functions.dialect import DUCK
from paircuration.operators.dedup import PRIME, coefficients

COLLAPSE = "trim(regexp_replace({0}, '[ \\t\\n\\r]+', ' ', 'g'))"
BARE_CODE = COLLAPSE.format("regexp_replace(code, '(#|//)[^\\n]*', '', 'g')")

Parts = list[tuple[str, str]]


def statement(parts: Parts, select: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(f"{n} AS ({s})" for n, s in parts) + "\n" + select


def exact(source: str, out: str, key: str, text: str) -> Parts:
    return [(out, f"SELECT * EXCLUDE (rn) FROM (SELECT *, row_number() OVER (PARTITION BY md5({text}) ORDER BY {key}) AS rn FROM {source}) WHERE rn = 1")]


def near(source: str, key: str, text: str, cfg: DedupConfig = DedupConfig()) -> Parts:
    """sets, sig, idx, cand over a deduplicated source."""
    mins = ", ".join(f"min(({a} * v + {b}) % {PRIME})" for a, b in coefficients(cfg))
    return [
        ("sets", f"SELECT {key} AS id, list_distinct(regexp_extract_all(lower({text}), '[a-z0-9_]+')) AS tokens FROM {source}"),
        ("sig", f"SELECT id, count(*) AS n_tokens, [{mins}] AS signature FROM (SELECT id, {DUCK.digest31('token')} AS v FROM (SELECT id, unnest(tokens) AS token FROM sets)) GROUP BY id"),
        ("idx", f"SELECT id, band, md5(array_to_string(signature[band * {cfg.rows} + 1 : band * {cfg.rows} + {cfg.rows}], ',')) AS key FROM sig, (SELECT unnest(range({cfg.bands})) AS band)"),
        ("cand", "SELECT DISTINCT a.id AS lo, b.id AS hi FROM idx a JOIN idx b ON a.band = b.band AND a.key = b.key AND a.id < b.id"),
    ]


def edges(mode: str, tau: float = 0.8) -> Parts:
    if mode == "none":
        return [("edges", "SELECT lo, hi, cast(NULL AS DOUBLE) AS sim FROM cand")]
    if mode == "signature":
        sim = "len(list_filter(list_zip(a.signature, b.signature), lambda x: x[1] = x[2])) / len(a.signature)"
        body = f"SELECT lo, hi, {sim} AS sim FROM cand JOIN sig a ON a.id = lo JOIN sig b ON b.id = hi"
    else:
        common = "len(list_intersect(a.tokens, b.tokens))"
        body = f"SELECT lo, hi, {common} / (len(a.tokens) + len(b.tokens) - {common}) AS sim FROM cand JOIN sets a ON a.id = lo JOIN sets b ON b.id = hi"
    return [("edges", f"SELECT * FROM ({body}) WHERE sim >= {tau}::DOUBLE")]


def greedy() -> Parts:
    """verdicts(id, kept) of the nodes that have edges, one node of the order per step."""
    return [
        ("nodes", "SELECT id, row_number() OVER (ORDER BY id) AS place, (SELECT list(lo) FROM edges e WHERE e.hi = n.id) AS earlier FROM (SELECT lo AS id FROM edges UNION SELECT hi FROM edges) n"),
        ("pass", "SELECT 0::BIGINT AS place, cast([] AS BIGINT[]) AS kept UNION ALL SELECT n.place, CASE WHEN len(list_intersect(coalesce(n.earlier, []), p.kept)) > 0 THEN p.kept ELSE list_append(p.kept, n.id) END FROM pass p JOIN nodes n ON n.place = p.place + 1"),
        ("verdicts", "SELECT id, list_contains((SELECT kept FROM pass ORDER BY place DESC LIMIT 1), id) AS kept FROM nodes"),
    ]


def components() -> Parts:
    return [
        ("reach", "SELECT id, id AS other FROM (SELECT lo AS id FROM edges UNION SELECT hi FROM edges) UNION SELECT r.id, e.o FROM reach r JOIN (SELECT lo AS i, hi AS o FROM edges UNION SELECT hi, lo FROM edges) e ON r.other = e.i"),
        ("verdicts", "SELECT id, min(other) AS root, min(other) = id AS kept FROM reach GROUP BY id"),
    ]


def functions() -> Parts:
    return [("fp", carriers.function_oracle())]


def stage1(cfg: Stage1Config = Stage1Config(), source: str = "fp") -> Parts:
    fails = R.stage1(DUCK, cfg)
    return [("judged", f"SELECT *, {', '.join(f'{v} AS f_{k}' for k, v in fails.items())} FROM {source}"),
            ("stage1", f"SELECT * FROM judged WHERE NOT ({' OR '.join(f'f_{k}' for k in fails)})")]


def scored(cfg: Stage2Config = Stage2Config(), source: str = "stage1", out: str = "scored") -> Parts:
    dims = R.dimensions(DUCK)
    raw = ", ".join(f"cast({dims[n]} AS DOUBLE) AS d_{n}" for n in DIMENSIONS)
    text = R.quality(DUCK, cfg)
    for n in DIMENSIONS:
        text = text.replace(f"cast({n} as", f"cast(d_{n} as")
    return [(out, f"SELECT *, {text} AS quality FROM (SELECT *, {raw} FROM {source})")]


def detected(cfg: DetectorConfig = DetectorConfig(), source: str = "fp", out: str = "detected") -> Parts:
    base = ", ".join(f"{v} AS {k}" for k, v in R.detector(DUCK, cfg).items())
    return [(out, f"SELECT *, {R.detector_tenths(DUCK, cfg)} AS ai_tenths, {R.matched(DUCK, cfg)} AS ai_matched, {R.detector_tenths(DUCK, cfg)} >= {cfg.tau_ai_tenths} AS ai_flag FROM (SELECT *, {base} FROM {source})")]


def curated(skip: str = "") -> Parts:
    """The whole chain with exact verification, one stage left out if named: cur has the kept pairs with quality and detector columns."""
    kept = exact("retained", "firsts", "pair_id", BARE_CODE) if skip != "exact" else [("firsts", "SELECT * FROM retained")]
    near_part = [*near("firsts", "pair_id", BARE_CODE), *edges("exact"), *greedy(), ("deduped", "SELECT * FROM firsts WHERE pair_id NOT IN (SELECT id FROM verdicts WHERE NOT kept)")]
    return [
        *functions(), *stage1(), *scored(source="fp" if skip == "stage1" else "stage1"), ("retained", f"SELECT * FROM scored WHERE {'true' if skip == 'stage2' else 'quality >= 6.0'}"),
        *kept, *(near_part if skip != "near" else [("deduped", "SELECT * FROM firsts")]), *detected(source="deduped", out="cur"),
    ]


SPLIT = """SELECT *, CASE WHEN r <= floor(total * '0.8'::DOUBLE) THEN 'train' WHEN r <= floor(total * '0.9'::DOUBLE) THEN 'validation' ELSE 'test' END AS split
FROM (SELECT *, row_number() OVER (PARTITION BY language ORDER BY md5('3407:' || pair_id), pair_id) AS r, count(*) OVER (PARTITION BY language) AS total FROM cur)"""
_TOKENS = "list_sort(list_distinct(regexp_extract_all(lower(code), '[a-z0-9_]+')))"


def retrieval(pools: str, cfg: DedupConfig = DedupConfig(num_hashes=64, bands=32, rows=2)) -> Parts:
    """gen(pool, pair_id, language, doc, template, found): for every row of `test` and each pool, the nearest function's documentation.

    `pools` is a SELECT of (pool, pair_id, doc, code).
    """
    mins = ", ".join(f"min(({a} * v + {b}) % {PRIME})" for a, b in coefficients(cfg))
    jac = "len(list_intersect(a.tokens, p.tokens))"
    return [
        ("members", f"SELECT pool, min(pair_id) AS id, arg_min(doc, pair_id) AS doc, tokens FROM (SELECT pool, pair_id, doc, {_TOKENS} AS tokens FROM ({pools})) GROUP BY pool, tokens"),
        ("asked", f"SELECT pair_id AS id, {_TOKENS} AS tokens FROM test"),
        ("flat", f"SELECT pool, id, {DUCK.digest31('token')} AS v FROM (SELECT pool, id, unnest(tokens) AS token FROM members UNION ALL SELECT '', id, unnest(tokens) FROM asked)"),
        ("sigs", f"SELECT pool, id, [{mins}] AS signature FROM flat GROUP BY pool, id"),
        ("banded", f"SELECT pool, id, band, array_to_string(signature[band * {cfg.rows} + 1 : band * {cfg.rows} + {cfg.rows}], ',') AS key FROM sigs, (SELECT unnest(range({cfg.bands})) AS band)"),
        ("proposed", "SELECT DISTINCT p.pool, a.id AS asked_id, p.id AS pool_id FROM banded a JOIN banded p ON a.pool = '' AND p.pool <> '' AND a.band = p.band AND a.key = p.key"),
        ("ranked", f"SELECT x.pool, asked_id, p.doc, row_number() OVER (PARTITION BY x.pool, asked_id ORDER BY {jac} / (len(a.tokens) + len(p.tokens) - {jac}) DESC, pool_id) AS place FROM proposed x JOIN asked a ON a.id = asked_id JOIN members p ON p.pool = x.pool AND p.id = pool_id"),
        ("gen", r"""SELECT n.pool, t.pair_id, t.language, t.doc, lower(regexp_replace(regexp_replace(t.name, '([a-z])([A-Z])', '\1 \2', 'g'), '_', ' ', 'g')) || ' ' || array_to_string(t.param_names, ' ') AS template, r.doc AS found
FROM test t CROSS JOIN (SELECT DISTINCT pool FROM members) n LEFT JOIN ranked r ON r.pool = n.pool AND r.asked_id = t.pair_id AND r.place = 1"""),
    ]
