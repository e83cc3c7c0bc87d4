"""Expressions of the filter, score and detector stages, as SQL text for either engine.

Each function returns named expressions over the pair columns (code, doc, name, param_names, typed_slots, slots,
return_type, language, complexity, logical_lines).
"""

from __future__ import annotations

from paircuration.config import DetectorConfig, Stage1Config, Stage2Config, DIMENSIONS

SECTIONS = (
    ("parameters", "(?m)^ *(Parameters|Args|Arguments):"),
    ("returns", "(?m)^ *Returns?:"),
    ("raises", "(?m)^ *(Raises|Throws):"),
    ("examples", "(?m)^ *Examples?:"),
)
DECISIONS = "(?m)^ *(if|for|while|elif|case|catch|switch) *[(]"


def first_line(d, text="doc"):
    return f"coalesce({d.at(d.split(text, chr(10)), 1)}, '')"


def section(d, name, text="doc"):
    if name == "description":
        return f"coalesce(trim({first_line(d, text)}) <> '' AND NOT {d.matches(first_line(d, text), '^ *(Parameters|Args|Arguments|Returns?|Raises|Throws|Examples?):')}, false)"
    return f"coalesce({d.matches(text, dict(SECTIONS)[name])}, false)"


def stage1(d, cfg: Stage1Config) -> dict[str, str]:
    """rule name -> true when the row FAILS it; nulls fail."""
    prefixes = "|".join(("get", "set", "is", "has"))
    if cfg.accessor_match == "prefix":
        accessor = d.matches("name", f"^({prefixes})")
    else:
        accessor = d.matches("name", f"^({prefixes})(_|[A-Z])")
        if cfg.accessor_match == "boundary_and_small":
            accessor = f"({accessor} AND logical_lines <= {cfg.accessor_max_lines})"
    test = {
        "substring": d.matches("name", "test|Test|TEST"),
        "affix": d.matches("name", "^(test|Test|TEST)|(_test|Test|TEST)$"),
        "boundary": d.matches("name", "^(test|TEST)(_|[A-Z]|$)|^Test([A-Z_]|$)|_test(_|$)|[a-z]Test([A-Z]|$)"),
    }[cfg.test_match]
    words = "(" + "|".join(cfg.placeholders) + ")"
    placeholder = d.matches("doc", words) if cfg.placeholder_case_sensitive else d.matches("lower(doc)", words.lower())
    rules = {
        "doc_too_short": f"length(doc) < {cfg.min_doc_chars}",
        "doc_too_long": f"length(doc) > {cfg.max_doc_chars}",
        "complexity_low": f"complexity < {cfg.min_complexity}",
        "complexity_high": f"complexity > {cfg.max_complexity}",
        "too_few_lines": f"logical_lines < {cfg.min_logical_lines}",
    }
    if cfg.max_logical_lines is not None:
        rules["too_many_lines"] = f"logical_lines > {cfg.max_logical_lines}"
    rules |= {"accessor": accessor, "test_code": test, "placeholder": placeholder}
    if cfg.exclude_examples:
        rules["examples"] = section(d, "examples")
    return {k: f"coalesce({v}, true)" for k, v in rules.items()}


def dimensions(d) -> dict[str, str]:
    """The eight dimension scores in [0, 1]; null where a row has no code side."""
    def num(cond):
        return f"CASE WHEN {cond} THEN 1.0 ELSE 0.0 END"

    words = d.find_all(first_line(d), "[^ ]+")
    all_words = d.find_all("lower(doc)", "[^ \n]+") if d.name == "spark" else "regexp_extract_all(lower(doc), '[^ ' || chr(10) || ']+')"
    described = d.keep("param_names", "p", "instr(doc, concat('  ', p, ':')) > 0")
    params, returns, raises, examples = (section(d, s) for s in ("parameters", "returns", "raises", "examples"))
    def spot(name):
        head = {"parameters": "Parameters:", "returns": "Returns:", "raises": "Raises:", "examples": "Examples:"}[name]
        return f"instr(doc, '{head}')"
    ordered = " AND ".join(f"({spot(a)} = 0 OR {spot(b)} = 0 OR {spot(a)} < {spot(b)})" for a, b in
                           (("parameters", "returns"), ("parameters", "raises"), ("parameters", "examples"), ("returns", "raises"), ("returns", "examples"), ("raises", "examples")))
    repeated = " OR ".join(f"{d.occurrences('doc', p)} > 1" for _, p in SECTIONS)
    lines = d.split("code", chr(10))
    long_lines = d.size(d.keep(lines, "x", "length(x) > 120"))
    names = d.find_all("code", "[A-Za-z_]+")
    deep = d.matches("code", "(?m)^ {24,}[^ ]")
    letters = f"length({d.replace('doc', '[^A-Za-z ]', '')})"
    return {
        "completeness": f"({num(section(d, 'description'))} + {num(f'{d.size(all_words)} >= 5')} + {num(f'{d.size("param_names")} = 0 OR {params}')} + {num(f'return_type IS NULL OR {returns}')}) / 4.0",
        "param_coverage": f"CASE WHEN param_names IS NULL THEN NULL WHEN {d.size('param_names')} = 0 THEN 1.0 ELSE {d.double(d.size(described))} / {d.size('param_names')} END",
        "return_doc": num(f"return_type IS NULL OR {returns}"),
        "types": f"CASE WHEN slots IS NULL THEN NULL WHEN slots = 0 THEN 1.0 ELSE {d.double('typed_slots')} / slots END",
        "clarity": f"({num(f'{d.size(words)} BETWEEN 3 AND 40')} + {num(f'{d.double(letters)} >= 0.7 * length(doc)')} + {num(f'lower({first_line(d)}) <> lower(name)')} + {num(f'{d.size(d.distinct(all_words))} >= 0.3 * {d.size(all_words)}')}) / 4.0",
        "structure": f"({num(ordered)} + {num(f'NOT ({repeated})')} + {num(section(d, 'description'))}) / 3.0",
        "complexity": f"CASE WHEN complexity IS NULL THEN NULL WHEN complexity BETWEEN 2 AND 10 THEN 1.0 WHEN complexity = 1 THEN 0.5 WHEN complexity BETWEEN 11 AND 50 THEN (50 - complexity) / 40.0 ELSE 0.0 END",
        "code_quality": f"({num(f'{long_lines} = 0')} + {num(f'length({d.join(names, "")}) >= 3 * {d.size(names)}')} + {num(f'NOT {deep}')} + {num('NOT ' + d.matches('code', 'TODO|FIXME'))}) / 4.0",
    }


def quality(d, cfg: Stage2Config, available: tuple[str, ...] = DIMENSIONS) -> str:
    """Weighted mean on 0..10 over columns named like the dimensions, rounded to six decimals."""
    pairs = [(n, w) for n, w in zip(DIMENSIONS, cfg.weights) if n in available or cfg.missing == "zero"]
    top = " + ".join(f"{w} * {d.double(n) if n in available else '0.0'}" for n, w in pairs)
    return f"round(10.0 * ({top}) / {sum(w for _, w in pairs)}.0, 6)"


def detector(d, cfg: DetectorConfig) -> dict[str, str]:
    """Four indicators, hit counts, tenths."""
    phrases = "(" + "|".join(cfg.phrases) + ")"
    generic = "(" + "|".join(cfg.generic) + ")"
    present = " + ".join(f"CASE WHEN {section(d, s)} THEN 1 ELSE 0 END" for s in ("description", "parameters", "returns", "raises", "examples"))
    bullets = d.keep(d.split("doc", chr(10)), "x", d.matches("x", "^- "))
    uniform = f"({d.size(bullets)} >= 3 AND {d.size(d.distinct(d.each(bullets, 'x', 'length(x)')))} = 1)"
    return {
        "phrase_hits": f"coalesce({d.occurrences('lower(doc)', phrases)}, 0)",
        "has_structure": f"coalesce({uniform}, false)",
        "section_count": f"coalesce({present}, 0)",
        "generic_hits": f"coalesce({d.occurrences('lower(doc)', generic)}, 0)",
    }


def detector_tenths(d, cfg: DetectorConfig) -> str:
    """Capped sum in tenths over the columns of `detector`."""
    if cfg.count == "per_signal":
        phrase, generic = "CASE WHEN phrase_hits > 0 THEN 3 ELSE 0 END", "CASE WHEN generic_hits > 0 THEN 1 ELSE 0 END"
    else:
        phrase, generic = "3 * phrase_hits", "generic_hits"
    return (f"cast(least(10, {phrase} + CASE WHEN has_structure THEN 2 ELSE 0 END + "
            f"CASE WHEN section_count >= {cfg.min_sections} THEN 2 ELSE 0 END + {generic}) as int)")


def matched(d, cfg: DetectorConfig) -> str:
    """Comma-joined names of the signals that fired."""
    flags = [("phrase", "phrase_hits > 0"), ("structure", "has_structure"), ("completeness", f"section_count >= {cfg.min_sections}"), ("generic", "generic_hits > 0")]
    items = d.array(*[f"CASE WHEN {c} THEN '{n}' ELSE '' END" for n, c in flags])
    return d.join(d.keep(items, "x", "x <> ''"), ",")
