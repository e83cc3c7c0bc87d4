"""URL filter: explicit host and path rules, and a ratio of two character language models for all other URLs.

Two variable-order Markov models (up to three symbols of context, Witten-Bell interpolation down to the uniform
distribution) are counted from URLs that a rule accepts and from URLs that a rule rejects.  A URL's score is the mean
log-likelihood difference per symbol of its host and path; the cut is the one with the best balanced accuracy on a
fifth of the ruled URLs that was held out of the counts.  DataFrame and SQL functions only.

Symbols are folded to 31 classes plus a start mark, so a model has at most 32^4 (about a million) four-symbol entries
whatever the input: that proven bound is what makes the model fit for broadcasting.

Defined results: null URLs and URLs without "://" have empty host and path, no rule and an empty string to score,
which scores 0; with no accepted or no rejected example every unruled URL is allowed.  Repeated rows are each judged;
an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from paircuration.llm.common import settle

# The rules, as (verdict, host, path prefix).
RULES = (
    ("block", "com", "/en/"),
    ("allow", "example.com", "/en/7"),
    ("allow", "net", "/de/"),
    ("block", "example.net", "/de/8"),
    ("block", "org", "/es/"),
)
ORDER, SYMBOLS = 4, 32
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_and_path(url: Column) -> tuple[Column, Column]:
    rest = F.when(F.instr(url, "://") > 0, F.substring_index(F.concat(F.lit("\x00"), url), "://", 1))
    after = F.when(rest.isNotNull(), F.substring(url, F.length(rest) + 3, F.length(url)))
    host = F.translate(F.regexp_extract(after, r"^[^/?#]*", 0), _UPPER, _LOWER)
    path = F.regexp_extract(after, r"^[^/?#]*([^?#]*)", 1)
    return F.coalesce(host, F.lit("")), F.coalesce(path, F.lit(""))


def ruled(rules: tuple) -> tuple[Column, Column]:
    """(rule, its verdict) of the longest rule that fits, else nulls."""
    rule, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for kind, host, path in sorted(rules, key=lambda r: len(r[1] + r[2])):
        fits = ((F.col("host") == host) | F.col("host").endswith("." + host)) & F.col("path").startswith(path)
        rule, verdict = F.when(fits, F.lit(host + path)).otherwise(rule), F.when(fits, F.lit(kind)).otherwise(verdict)
    return rule, verdict


def _symbols(text: Column) -> Column:
    """Folded symbols 1..31: letters, any digit, dot, dash, slash, anything else."""
    def fold(ch):
        code = F.ascii(ch)
        return (F.when((code >= 97) & (code <= 122), code - 96).when((code >= 48) & (code <= 57), F.lit(27))
                .when(code == 46, F.lit(28)).when(code == 45, F.lit(29)).when(code == 47, F.lit(30)).otherwise(F.lit(31)))
    return F.when(F.length(text) > 0, F.transform(F.split(F.translate(text, _UPPER, _LOWER), ""), fold)).otherwise(F.expr("cast(array() as array<int>)"))


def _grams(symbols: Column) -> Column:
    """Each position's symbol with the three before it (zeros before the start), packed into 20 bits."""
    def packed(symbol, i):
        for back in range(1, ORDER):
            symbol = symbol + F.coalesce(F.get(symbols, i - back), F.lit(0)) * (SYMBOLS ** back)
        return symbol
    return F.transform(symbols, packed)


def train(urls: DataFrame) -> DataFrame:
    """Model (gram, ratio): log P(symbol | context) under accepted minus under rejected, for every gram in the input.

    `urls` has columns spelled (the string) and label (1 accepted, 0 rejected, null neither).
    """
    flat = urls.select("label", _symbols(F.col("spelled")).alias("symbols")).select("label", F.explode(_grams(F.col("symbols"))).alias("gram"))
    full = settle(flat.groupBy("gram").agg(F.count_if(F.col("label") == 1).alias("a"), F.count_if(F.col("label") == 0).alias("b")), "grams")
    model = None
    for k in range(1, ORDER + 1):
        level = full.groupBy(F.col("gram").bitwiseAND(F.lit((1 << (5 * k)) - 1)).alias("gram")).agg(F.sum("a").alias("a"), F.sum("b").alias("b"))
        level = level.withColumn("context", F.shiftright("gram", 5))
        around = level.groupBy("context").agg(
            F.sum("a").alias("na"), F.sum("b").alias("nb"), F.count_if(F.col("a") > 0).alias("ta"), F.count_if(F.col("b") > 0).alias("tb"))
        level = level.join(F.broadcast(around), "context")  # at most 32^3 contexts
        if model is None:
            level = level.withColumn("la", F.lit(1.0 / SYMBOLS)).withColumn("lb", F.lit(1.0 / SYMBOLS))
        else:  # at most 32^3 shorter grams
            level = level.withColumn("shorter", F.col("gram").bitwiseAND(F.lit((1 << (5 * (k - 1))) - 1)))
            level = level.join(F.broadcast(model.select(F.col("gram").alias("shorter"), F.col("pa").alias("la"), F.col("pb").alias("lb"))), "shorter")
        def smooth(n, total, kinds, lower):
            return F.when(F.col(total) > 0, (F.col(n) + F.col(kinds) * F.col(lower)) / (F.col(total) + F.col(kinds))).otherwise(F.col(lower))
        model = level.select("gram", smooth("a", "na", "ta", "la").alias("pa"), smooth("b", "nb", "tb", "lb").alias("pb"))
        if k < ORDER:
            model = settle(model, "orders")
    return settle(model.select("gram", F.log(F.col("pa") / F.col("pb")).alias("ratio")), "url-model")


def scored(urls: DataFrame, model: DataFrame) -> DataFrame:
    """`urls` grouped by all its columns, with copies (how many equal rows) and score (mean ratio per symbol).

    Positions are summed map-side right after they are made, so one row per URL is shuffled.
    """
    names = urls.columns
    flat = urls.select(*names, _symbols(F.col("spelled")).alias("_symbols"))
    flat = flat.select(*names, F.greatest(F.size("_symbols"), F.lit(1)).alias("_sites"), F.explode_outer(_grams(F.col("_symbols"))).alias("_gram"))
    met = flat.join(F.broadcast(model.toDF("_gram", "_ratio")), "_gram", "left")  # bounded by the alphabet: at most 32^4 rows
    return met.groupBy(*names, "_sites").agg(F.count(F.lit(1)).alias("_positions"), F.coalesce(F.sum("_ratio"), F.lit(0.0)).alias("_total")).select(
        *names, (F.col("_positions") / F.col("_sites")).cast("int").alias("copies"), (F.col("_total") / F.col("_positions")).alias("score"))


def calibrate(held: DataFrame) -> float:
    """Cut with the best balanced accuracy over at most 401 score bins; `held` has score and label (1 or 0)."""
    bins = held.groupBy(F.greatest(F.lit(-200), F.least(F.lit(200), F.round(F.col("score") * 50))).cast("int").alias("bin")).agg(
        F.sum((F.col("label") == 1).cast("bigint") * F.col("copies")).alias("a"), F.sum((F.col("label") == 0).cast("bigint") * F.col("copies")).alias("b"))
    rows = sorted(bins.collect())
    all_a, all_b = sum(r["a"] for r in rows), sum(r["b"] for r in rows)
    if not all_a or not all_b:
        return float("-inf")
    best, cuts, below_a, below_b = -1.0, [], 0, 0
    edges = [rows[0]["bin"] - 1] + [r["bin"] for r in rows]
    for i, edge in enumerate(edges):
        if i:
            below_a, below_b = below_a + rows[i - 1]["a"], below_b + rows[i - 1]["b"]
        worth = (all_a - below_a) / all_a + below_b / all_b
        nxt = edges[i + 1] if i + 1 < len(edges) else edge + 1
        if worth > best + 1e-12:
            best, cuts = worth, []
        if worth >= best - 1e-12:
            cuts.append((edge + nxt) / 100.0)
    return cuts[len(cuts) // 2]


def judge(df: DataFrame, rules: tuple = RULES, id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """One row per input row: id, url, host, path, rule, score, cut, verdict (the rule's, else the models')."""
    host, path = host_and_path(F.col("link"))
    urls = df.select(F.col(id_col).alias("row_key"), F.col(url_col).cast("string").alias("link")).withColumn("host", host).withColumn("path", path)
    rule, verdict = ruled(rules)
    urls = urls.withColumn("rule", rule).withColumn("ruling", verdict).withColumn("spelled", F.concat("host", "path"))
    label = F.when(F.col("ruling") == "allow", 1).when(F.col("ruling") == "block", 0)
    held = F.pmod(F.xxhash64("spelled"), F.lit(5)) == 0
    model = train(urls.select("spelled", F.when(~held, label).alias("label")))
    found = settle(scored(urls, model), "url-scores")
    cut = calibrate(found.filter(held & F.col("ruling").isNotNull()).withColumn("label", label))
    return found.withColumn("copy", F.explode(F.sequence(F.lit(1), "copies"))).select(
        F.col("row_key").alias(id_col), F.col("link").alias(url_col), "host", "path", "rule", "score", F.lit(cut).alias("cut"),
        F.coalesce("ruling", F.when(F.col("score") >= cut, "allow").otherwise("block")).alias("verdict"))


def op4_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(spark.read.parquet(f"{sf_dir}/pages.parquet")).select("page_id", "host", "path", "rule", "score", "verdict")
