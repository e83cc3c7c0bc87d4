"""Pair carriers over the given tables: the rows that the curation stages work on.

C0 takes documents as they are; C1 renders deterministic functions from them (the given tables hold no source code);
C2 pairs page titles with articles; C3 pairs replies with the turn before; C4 joins the labels.
All are projections (C3 and C4 one join), written once for both SQL engines.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from paircuration.functions.dialect import DUCK, SPARK
from paircuration.sources import tables

PREFIXES = ("get", "set", "is", "has", "test", "compute", "parse", "latest", "issue", "load", "merge", "build")
PHRASE = "It is important to note that this function is designed to help."
GENERIC = "Utility function that performs the operation."
FUNCTION_COLUMNS = (
    "pair_id", "repo", "path", "language", "name", "param_names", "typed_slots", "slots", "return_type", "code", "doc", "complexity", "logical_lines",
)


def function_sql(d, source: str = "documents") -> str:
    """SELECT of C1 with its planted truth, for one engine. Every choice has a digest of its own."""
    def h(name):
        return d.digest_int(f"concat(g, '{name}')")

    def pick(options, number):
        return d.at(d.array(*[d.lit(o) for o in options]), f"({number}) % {len(options)} + 1")

    def camel(x):
        return f"concat(upper(substr({x}, 1, 1)), substr({x}, 2))"

    words = f"""SELECT doc_id, source, lang, text, {d.find_all('lower(text)', '[a-z]+')} AS w FROM {source} WHERE text IS NOT NULL"""
    seeded = f"SELECT *, md5({d.join(d.part('w', 1, 5), ' ')}) AS g FROM ({words}) words"
    chosen = f"""
SELECT *, CASE lang WHEN 'de' THEN 'typescript' WHEN 'fr' THEN 'javascript' WHEN 'es' THEN 'cpp'
         ELSE CASE WHEN {h('language')} % 2 = 0 THEN 'java' ELSE 'python' END END AS language,
       {pick(PREFIXES, h('prefix'))} AS prefix, coalesce({d.at('w', 6)}, 'item') AS word_a, coalesce({d.at('w', 7)}, 'value') AS word_b,
       {d.indexed(d.part('w', 8, f"{h('params')} % 4"), 'x', 'i', "concat(x, '_', cast({i} as " + d.texts() + "))")} AS param_names,
       CASE WHEN {h('returns')} % 4 = 0 THEN NULL ELSE {pick(('int', 'str', 'list', 'bool'), h('return_type'))} END AS return_type,
       {h('typed')} % 5 < 2 AS dice_typed, {h('cap')} % 53 = 0 AS is_capped, {h('placeholder')} % 17 = 0 AS is_placeholder,
       {h('phrase')} % 13 = 0 AS is_phrase, {h('phrases')} % 39 = 0 AS is_phrases, {h('generic')} % 7 = 0 AS is_generic,
       {h('bullets')} % 19 = 0 AS is_bullets, {h('examples')} % 11 = 0 AS is_examples, {h('raises')} % 4 = 0 AS is_raises,
       {h('sections')} % 3 AS section_choice, {h('return_doc')} % 3 > 0 AS is_return_doc, {h('keyword')} AS keyword_choice
FROM ({seeded}) seeded"""
    comment = "CASE WHEN language = 'python' THEN '# ' ELSE '// ' END"
    keyword = pick(("if", "for", "while"), "keyword_choice")
    line = (f"CASE WHEN {{i}} % 7 = 0 THEN concat({comment}, {d.join(d.part('w', '({i} - 1) * 6 + 6', 6), ' ')}) "
            f"WHEN {{i}} % 5 = 0 THEN concat({keyword}, ' (', {d.join(d.part('w', '({i} - 1) * 6 + 6', 6), ' < ')}, '):') "
            f"ELSE concat({d.join(d.part('w', '({i} - 1) * 6 + 6', 6), ' + ')}, ';') END")
    body = d.indexed(d.keep(d.range(20), "k", f"(k - 1) * 6 + 6 <= {d.size('w')}"), "x", "i", line)
    many = d.each(d.range(55), "k", "concat('if (branch_', cast(k as " + d.texts() + "), '):')")
    built = f"""
SELECT *, CASE WHEN language IN ('java', 'typescript', 'cpp') THEN true WHEN language = 'python' THEN dice_typed ELSE false END AS is_typed,
       CASE WHEN language IN ('python', 'cpp') THEN concat(prefix, '_', word_a, '_', word_b) ELSE concat(prefix, {camel('word_a')}, {camel('word_b')}) END AS name,
       {d.extend(body, f"CASE WHEN is_capped THEN {many} ELSE {d.no_strings()} END")} AS body_lines,
       {d.at(d.split('text', chr(10)), 1)} AS summary
FROM ({chosen}) chosen"""
    documented = f"CASE section_choice WHEN 0 THEN param_names WHEN 1 THEN {d.part('param_names', 1, f'cast(floor({d.size("param_names")} / 2.0) as int)')} ELSE {d.no_strings()} END"
    parts = f"""
SELECT *, {documented} AS documented,
       concat(CASE language WHEN 'python' THEN 'def ' WHEN 'javascript' THEN 'function ' ELSE '' END, name, '(',
              {d.join(d.each('param_names', 'x', "CASE WHEN is_typed THEN concat(x, ': int') ELSE x END"), ', ')}, ')',
              CASE WHEN is_typed AND return_type IS NOT NULL THEN concat(' -> ', return_type) ELSE '' END, ' {{') AS header
FROM ({built}) built"""
    def block(flag, *lines):
        return f"CASE WHEN {flag} THEN {d.array(*lines)} ELSE {d.no_strings()} END"
    doc = d.extend(
        d.array("summary"), block("is_placeholder", d.lit("TODO: describe")), block("is_phrase", d.lit(PHRASE)),
        block("is_phrases", *[d.lit(PHRASE)] * 4), block("is_generic", d.lit(GENERIC)),
        block("is_bullets", d.lit("- step done"), d.lit("- step next"), d.lit("- step last")),
        block(f"{d.size('documented')} > 0", d.lit("Parameters:")),
        d.each("documented", "x", "concat('  ', x, ': the ', x, ' of ', word_b)"),
        block("is_return_doc AND return_type IS NOT NULL", d.lit("Returns:"), "concat('  ', return_type, ' made from ', word_a)"),
        block("is_raises", d.lit("Raises:"), d.lit("  ValueError: if the input is empty")),
        block("is_examples", d.lit("Examples:"), "concat('  ', name, '(1)')"))
    logical = d.size(d.keep("body_lines", "x", f"trim(x) <> '' AND NOT {d.matches('x', '^(#|//)')}"))
    return f"""
SELECT doc_id AS pair_id, source AS repo, concat(source, '/', g, '.', language) AS path, language, name, param_names,
       cast(CASE WHEN is_typed THEN {d.size('param_names')} + CASE WHEN return_type IS NULL THEN 0 ELSE 1 END ELSE 0 END as int) AS typed_slots,
       cast({d.size('param_names')} + CASE WHEN return_type IS NULL THEN 0 ELSE 1 END as int) AS slots, return_type,
       concat(header, {d.lit(chr(10))}, {d.join('body_lines', chr(10))}, {d.lit(chr(10) + '}')}) AS code, {d.join(doc, chr(10))} AS doc,
       cast(1 + {d.size(d.keep('body_lines', 'x', d.matches('x', '^(if|for|while) [(]')))} as int) AS complexity, cast({logical} + 1 as int) AS logical_lines,
       is_placeholder, is_phrase OR is_phrases AS is_phrase, is_generic, is_bullets, is_examples, is_capped
FROM ({parts}) parts"""


LICENCES = ("mit", "apache-2.0", "gpl-3.0", "proprietary")


def source_sql(d, source: str) -> str:
    """SELECT of one small source file per function of C1, in its language's own syntax, with what should be read back.

    The file holds the function's name, parameters, types, summary and as many decisions as C1 counts.  Repositories get
    a licence and idle days from digests of their names.
    """
    summary = f"trim({d.replace(d.replace(d.at(d.split('doc', chr(10)), 1), '[^A-Za-z0-9 ]', ' '), '[ ]+', ' ')})"
    typed, nl = "typed_slots > 0", d.lit(chr(10))
    def params(before, after):
        return d.join(d.each("param_names", "x", f"concat({before}, x, {after})"), ", ")
    none, suffix = d.lit(""), f"CASE WHEN {typed} THEN {d.lit(': int')} ELSE {d.lit('')} END"
    branches = f"repeat(concat({d.lit('    if (flag) { step(); }')}, {nl}), complexity - 1)"
    tail = f"{branches}, {d.lit('    return 0;')}, {nl}, {d.lit('}')}, {nl}"
    block = f"CASE WHEN summary <> '' THEN concat({d.lit('/** ')}, summary, {d.lit(' */')}, {nl}) ELSE '' END"
    text = f"""CASE language
WHEN 'python' THEN concat({d.lit('def ')}, name, '(', {params(none, suffix)}, ')', CASE WHEN {typed} AND return_type IS NOT NULL THEN concat({d.lit(' -> ')}, return_type) ELSE '' END, ':', {nl},
  CASE WHEN summary <> '' THEN concat({d.lit('    """')}, summary, {d.lit('"""')}, {nl}) ELSE '' END, repeat(concat({d.lit('    if flag: step()')}, {nl}), complexity - 1), {d.lit('    return 0')}, {nl})
WHEN 'javascript' THEN concat({block}, {d.lit('function ')}, name, '(', {params(none, none)}, {d.lit(') {')}, {nl}, {tail})
WHEN 'typescript' THEN concat({block}, {d.lit('function ')}, name, '(', {params(none, d.lit(': int'))}, ')', CASE WHEN return_type IS NOT NULL THEN concat(': ', return_type) ELSE '' END, {d.lit(' {')}, {nl}, {tail})
ELSE concat({block}, CASE WHEN language = 'java' THEN {d.lit('public ')} ELSE '' END, coalesce(return_type, 'void'), ' ', name, '(', {params(d.lit('int '), none)}, {d.lit(') {')}, {nl}, {tail}) END"""
    kind = f"CASE WHEN language IN ('java', 'cpp') THEN coalesce(return_type, 'void') WHEN language = 'typescript' OR (language = 'python' AND {typed}) THEN return_type END"
    licence = d.at(d.array(*[d.lit(x) for x in LICENCES]), f"{d.digest_int('concat(repo, ' + d.lit(':licence') + ')')} % {len(LICENCES)} + 1")
    return f"""SELECT concat(repo, '/', cast(pair_id as {d.texts()}), '.', language) AS path, repo, language, {text} AS source, {licence} AS licence,
       {d.digest_int('concat(repo, ' + d.lit(':idle') + ')')} % 720 AS idle_days, concat({d.lit('https://example.org/')}, repo) AS url,
       name, {d.join('param_names', ',')} AS params, {kind} AS kind, CASE WHEN summary <> '' THEN summary END AS doc, complexity
FROM (SELECT *, {summary} AS summary FROM {source}) summarised"""


def text_sql(source: str = "documents") -> str:
    return f"SELECT doc_id AS pair_id, source AS repo, lang AS language, text AS code, text AS doc FROM {source}"


def page_sql(d, source: str = "pages") -> str:
    plain = d.replace("split_part(split_part(html, '<article>', 2), '</article>', 1)", '<[^>]*>', ' ')
    return (f"SELECT page_id, url, {d.extract('html', '<title>([^<]*)</title>')} AS doc, trim({d.replace(plain, '[ ]+', ' ')}) AS code FROM {source}")


def reply_sql(source: str = "conversations") -> str:
    return f"""SELECT a.conv_id, a.turn, a.text AS candidate, u.text AS reference FROM {source} a
JOIN {source} u ON a.conv_id = u.conv_id AND a.turn = u.turn + 1 AND a.role = 'assistant' AND u.role = 'user'"""


def function_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """C1 without its planted truth."""
    return tables.run_sql(spark, function_sql(SPARK, "@docs@"), docs=tables.load(spark, sf_dir, "documents")).select(*FUNCTION_COLUMNS)


def text_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tables.run_sql(spark, text_sql("@docs@"), docs=tables.load(spark, sf_dir, "documents"))


def page_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tables.run_sql(spark, page_sql(SPARK, "@pages@"), pages=tables.load(spark, sf_dir, "pages"))


def reply_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tables.run_sql(spark, reply_sql("@turns@"), turns=tables.load(spark, sf_dir, "conversations"))


def function_oracle() -> str:
    return f"SELECT {', '.join(FUNCTION_COLUMNS)} FROM ({function_sql(DUCK)}) rendered"
