"""Repository choice and extraction of functions with their documentation from source files.

Defined results: a null, empty or unreadable file has no functions; a file of an unknown language has none; repeated files
are read each; very long files are parsed whole, one at a time; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import ast
import re

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

SCHEMA = "path string, language string, name string, params array<struct<name:string,type:string,has_default:boolean>>, return_type string, code string, doc string, complexity int, logical_lines int, first_line int, last_line int"
_BRANCH = (ast.If, ast.For, ast.AsyncFor, ast.While, ast.ExceptHandler, ast.IfExp, ast.comprehension, ast.Assert)


def select_repos(df: DataFrame, repo: str = "repo", min_rows: int = 1, min_doc_rate: float = 0.0, licences: list[str] | None = None,
                 domain: str | None = None, per_domain: int | None = None, doc: str = "doc", max_idle_days: int | None = None) -> DataFrame:
    """Rows of repositories that pass adoption, documentation, licence, activity and diversity tests.

    Statistics come from one combined aggregate; the chosen repositories return by a semi join.  Columns `licence` and
    `idle_days` are read only if their test is on.  Rows without a repository are never chosen; an empty table gives none.
    """
    measures = [F.count(F.lit(1)).alias("rows"), F.avg((F.length(F.trim(F.coalesce(doc, F.lit("")))) > 0).cast("int")).alias("doc_rate")]
    if licences is not None:
        measures.append(F.min("licence").alias("licence"))
    if max_idle_days is not None:
        measures.append(F.min("idle_days").alias("idle_days"))
    if domain:
        measures.append(F.min(domain).alias("domain"))
    stats = df.groupBy(repo).agg(*measures).filter((F.col("rows") >= min_rows) & (F.col("doc_rate") >= min_doc_rate))
    if licences is not None:
        stats = stats.filter(F.col("licence").isin(licences))
    if max_idle_days is not None:
        stats = stats.filter(F.col("idle_days") <= max_idle_days)
    if domain and per_domain:
        stats = stats.withColumn("place", F.row_number().over(Window.partitionBy("domain").orderBy(F.desc("rows"), repo))).filter(F.col("place") <= per_domain)
    return df.join(stats.select(repo), repo, "left_semi")


def cyclomatic_ast(node: ast.AST) -> int:
    """One plus the decisions of a function, nested functions left out; each extra boolean operand counts."""
    total, todo = 1, list(ast.iter_child_nodes(node))
    while todo:
        n = todo.pop()
        if isinstance(n, (ast.FunctionDef, ast.AsyncFunctionDef, ast.Lambda, ast.ClassDef)):
            continue
        total += isinstance(n, _BRANCH) + (len(n.values) - 1 if isinstance(n, ast.BoolOp) else 0)
        todo.extend(ast.iter_child_nodes(n))
    return total


def _logical(code: str, comment: str) -> int:
    return sum(1 for line in code.split("\n") if line.strip() and not line.strip().startswith(comment))


def parse_python(path: str, source: str) -> list[tuple]:
    """Functions of a Python file by its syntax tree; an unreadable file has none."""
    try:
        tree = ast.parse(source)
    except (SyntaxError, ValueError, RecursionError):
        return []
    found = []
    for node in ast.walk(tree):
        if isinstance(node, (ast.FunctionDef, ast.AsyncFunctionDef)):
            args = node.args.posonlyargs + node.args.args
            defaults = len(args) - len(node.args.defaults)
            params = [(a.arg, ast.unparse(a.annotation) if a.annotation else None, i >= defaults) for i, a in enumerate(args)]
            params += [(a.arg, ast.unparse(a.annotation) if a.annotation else None, d is not None) for a, d in zip(node.args.kwonlyargs, node.args.kw_defaults)]
            code = ast.get_source_segment(source, node) or ""
            found.append((path, "python", node.name, params, ast.unparse(node.returns) if node.returns else None, code, ast.get_docstring(node),
                          cyclomatic_ast(node), _logical(code, "#"), node.lineno, node.end_lineno))
    return found


_HEADERS = {
    "javascript": re.compile(r"^[ \t]*(?:export\s+)?(?:async\s+)?function\s+([A-Za-z_$][\w$]*)\s*\(([^)]*)\)\s*\{", re.M),
    "typescript": re.compile(r"^[ \t]*(?:export\s+)?(?:async\s+)?(?:function\s+)?([A-Za-z_$][\w$]*)\s*\(([^)]*)\)\s*(?::\s*([^{]+?))?\s*\{", re.M),
    "java": re.compile(r"^[ \t]*(?:(?:public|private|protected|static|final|synchronized)\s+)*([\w<>\[\], ?]+?)\s+([A-Za-z_]\w*)\s*\(([^)]*)\)\s*(?:throws\s+[\w, .]+)?\{", re.M),
    "cpp": re.compile(r"^[ \t]*(?:(?:static|inline|virtual|constexpr)\s+)*([\w:<>*& ,]+?)\s+([A-Za-z_][\w:]*)\s*\(([^)]*)\)\s*(?:const\s*)?\{", re.M),
}
_RESERVED = {"if", "for", "while", "switch", "catch", "return", "else", "new"}


def _close(source: str, at: int) -> int:
    """Index just past the brace that closes the one at `at`, skipping strings and comments."""
    depth, i, n = 0, at, len(source)
    while i < n:
        c = source[i]
        if c in "\"'`":
            i += 1
            while i < n and source[i] != c:
                i += 2 if source[i] == "\\" else 1
        elif source.startswith("//", i):
            i = source.find("\n", i)
            if i < 0:
                return n
        elif source.startswith("/*", i):
            i = source.find("*/", i) + 1
            if i <= 0:
                return n
        elif c == "{":
            depth += 1
        elif c == "}":
            depth -= 1
            if depth == 0:
                return i + 1
        i += 1
    return n


def parse_braced(path: str, source: str, language: str) -> list[tuple]:
    """Functions of a brace language by a lexical scan; the documentation is the block comment just before."""
    found = []
    for m in _HEADERS[language].finditer(source):
        if language in ("java", "cpp"):
            kind, name, args = m[1].strip(), m[2], m[3]
        elif language == "typescript":
            kind, name, args = (m[3] or "").strip() or None, m[1], m[2]
        else:
            kind, name, args = None, m[1], m[2]
        if name in _RESERVED or kind in _RESERVED:
            continue
        params = []
        for a in filter(None, (x.strip() for x in args.split(","))):
            left, _, default = a.partition("=")
            if language in ("java", "cpp"):
                t, _, p = left.strip().rpartition(" ")
                params.append((p.lstrip("*&"), t or None, bool(default)))
            else:
                p, _, t = left.partition(":")
                params.append((p.strip().rstrip("?"), t.strip() or None, bool(default)))
        end = _close(source, m.end() - 1)
        code = source[m.start() : end].lstrip("\n")
        before = re.search(r"/\*\*?((?:[^*]|\*(?!/))*)\*/\s*\Z", source[: m.start()])
        doc = "\n".join(re.sub(r"^\s*\*? ?", "", line) for line in before[1].strip().split("\n")) if before else None
        body = re.sub(r"\"(?:[^\"\\]|\\.)*\"|'(?:[^'\\]|\\.)*'|//[^\n]*|/\*(?:[^*]|\*(?!/))*\*/", " ", code)
        branches = len(re.findall(r"\b(?:if|for|while|case|catch)\b|&&|\|\||\?(?![.:?])", body))
        first = source.count("\n", 0, m.start()) + 1
        found.append((path, language, name, params, kind, code, doc, 1 + branches, _logical(code, "//"), first, first + code.count("\n")))
    return found


def extract_functions(df: DataFrame, path: str = "path", source: str = "source", language: str = "language") -> DataFrame:
    """Pair rows of source files: syntax trees for python, lexical scans for the brace languages. Narrow."""
    names = [f.split(" ")[0] for f in SCHEMA.split(", ")[:3]] + ["params", "return_type", "code", "doc", "complexity", "logical_lines", "first_line", "last_line"]

    def run(frames):
        for pdf in frames:
            rows = []
            for p, s, g in zip(pdf["path"], pdf["source"], pdf["language"]):
                if s is not None:
                    rows += parse_python(p, s) if g == "python" else parse_braced(p, s, g) if g in _HEADERS else []
            yield pd.DataFrame([tuple([{"name": a, "type": b, "has_default": c} for a, b, c in v] if i == 3 else v for i, v in enumerate(r)) for r in rows], columns=names)

    return df.select(F.col(path).alias("path"), F.col(source).alias("source"), F.col(language).alias("language")).mapInPandas(run, SCHEMA)


def cyclomatic_proxy(code: Column) -> Column:
    """One plus conditional and loop words outside strings and comments: the estimate when no tree is at hand."""
    bare = F.regexp_replace(code, r"\"(?:[^\"\\\\\n]|\\\\.)*+\"|'(?:[^'\\\\\n]|\\\\.)*+'|//[^\n]*|#[^\n]*", " ")
    return 1 + F.regexp_count(bare, F.lit(r"\b(if|elif|for|while|case|catch|except)\b"))


def doc_of(code: Column, language: Column) -> Column:
    """Docstring of a python body, or the block comment at the head of another one; null if there is none."""
    python = F.regexp_extract(code, r'^[^\n]*:\s*\n\s*"{3}([^"]*)"{3}', 1)
    other = F.regexp_extract(code, r"^\s*/[*]{1,2}((?:[^*]|[*](?!/))*+)[*]/", 1)
    found = F.trim(F.when(language == "python", python).otherwise(other))
    return F.when(found != "", found)


def signature(header: Column) -> Column:
    """array<struct<name,type,has_default>> of a `name(a: T = 1, b)` header."""
    inside = F.regexp_extract(header, r"[(]([^)]*)[)]", 1)
    items = F.filter(F.transform(F.split(inside, ","), lambda x: F.trim(x)), lambda x: x != "")
    return F.transform(items, lambda x: F.struct(
        F.regexp_extract(x, r"^([A-Za-z_$][\w$]*)", 1).alias("name"), F.nullif(F.trim(F.regexp_extract(x, r":\s*([^=]+)", 1)), F.lit("")).alias("type"), F.contains(x, F.lit("=")).alias("has_default")))


def pairs(extracted: DataFrame, files: DataFrame, version: str, path: str = "path") -> DataFrame:
    """Pair rows of the curation stages from extracted functions and the files they came from.

    `files` has path, repo, licence and url, one row per path.  Every row carries its origin as `meta`: repository, path,
    line span, licence, address and version.  The complexity of a syntax tree or scan is kept; where it is missing, the
    keyword estimate stands in.
    """
    origin = files.select(F.col(path).alias("path"), "repo", "licence", "url")
    typed = F.size(F.filter("params", lambda x: x["type"].isNotNull())) + F.col("return_type").isNotNull().cast("int")
    meta = F.struct("repo", "path", "first_line", "last_line", "licence", "url", F.lit(version).alias("version"))
    return extracted.join(origin, "path").select(
        F.concat_ws(":", "path", F.col("first_line").cast("string")).alias("pair_id"), "repo", "path", "language", "name", F.col("params.name").alias("param_names"),
        typed.alias("typed_slots"), (F.size("params") + F.col("return_type").isNotNull().cast("int")).alias("slots"), "return_type", "code", "doc",
        F.coalesce("complexity", cyclomatic_proxy(F.col("code")).cast("int")).alias("complexity"), "logical_lines", meta.alias("meta"))


def temporal_cutoff(df: DataFrame, ts: str, before: str) -> DataFrame:
    """Rows from before a moment; the comparison reaches the scan."""
    return df.filter(F.col(ts) < F.lit(before).cast(df.schema[ts].dataType))
