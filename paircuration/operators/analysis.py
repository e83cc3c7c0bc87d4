"""Corpus statistics: summary, shares, histograms, coverage, funnel, sweeps, agreement.

Defined results: repeated rows count as often as they occur; null group keys form a group of their own; null values enter
no mean, median or histogram bound but their rows are counted; tied groups rank by their key; an empty table gives no
groups, or one row with zero counts and null measures; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from paircuration.operators import relational


def median(df: DataFrame, value: str) -> DataFrame:
    """One row: the exact median, as the middle rows of a distributed ranking; null without values."""
    known = df.select(F.col(value).cast("double").alias("v")).filter("v IS NOT NULL")
    ranked = relational.global_rank(known, [F.col("v")], "place")
    n = known.agg(F.count(F.lit(1)).alias("n"))
    return ranked.join(F.broadcast(n), F.expr("place = div(n - 1, 2) OR place = div(n, 2)")).agg(F.avg("v").alias(value))


def summary(df: DataFrame, exact: bool = True) -> DataFrame:
    """One row; medians exact by ranking, or by a sketch whose size is fixed.  An empty table has null statistics."""
    middle = {c: median(df, c).first()[0] if exact else None for c in ("quality", "complexity")}
    at = (lambda c: F.lit(middle[c]).cast("double")) if exact else (lambda c: F.percentile_approx(c, 0.5, 10_000))
    return df.agg(
        F.count(F.lit(1)).alias("pairs"), F.avg("quality").alias("quality_mean"), F.first(at("quality")).alias("quality_median") if exact else at("quality").alias("quality_median"),
        F.stddev_samp("quality").alias("quality_sd"), F.min("quality").alias("quality_min"), F.max("quality").alias("quality_max"),
        F.avg("complexity").alias("complexity_mean"), F.first(at("complexity")).alias("complexity_median") if exact else at("complexity").alias("complexity_median"),
        F.count_if(F.col("typed_slots") > 0).alias("typed"), F.count_if("ai_flag").alias("flagged"))


def shares(df: DataFrame, by: str) -> DataFrame:
    counts = df.groupBy(by).agg(F.count(F.lit(1)).alias("n"))
    return counts.withColumn("share", F.col("n") / F.sum("n").over(Window.partitionBy(F.lit(1))))


def quartiles(df: DataFrame, by: str, value: str) -> DataFrame:
    return df.groupBy(by).agg(F.count(F.lit(1)).alias("n"), F.avg(value).alias("mean"), *[F.percentile(value, q).alias(name) for name, q in (("q1", 0.25), ("median", 0.5), ("q3", 0.75))])


def histogram(df: DataFrame, value: str, width: float) -> DataFrame:
    return df.groupBy((F.floor(F.col(value) / width) * width).cast("double").alias("low")).agg(F.count(F.lit(1)).alias("n"))


def coverage(df: DataFrame, by: str) -> DataFrame:
    """Rank, count and cumulative share per group, by a distributed running sum over the groups' counts."""
    counts = df.groupBy(by).agg(F.count(F.lit(1)).alias("n"))
    run = relational.global_run(counts, [F.desc("n"), F.col(by)], {"place": F.lit(1).cast("bigint"), "upto": F.col("n")})
    total = df.agg(F.count(F.lit(1)).alias("total"))
    return run.join(F.broadcast(total), F.lit(True)).select(by, "n", "place", F.try_divide("upto", "total").alias("cumulative"))


def gini(df: DataFrame, by: str) -> DataFrame:
    """One row: inequality of the groups' sizes; null without groups."""
    counts = df.groupBy(by).agg(F.count(F.lit(1)).alias("n"))
    ranked = relational.global_run(counts, [F.col("n"), F.col(by)], {"i": F.lit(1).cast("bigint")})
    groups = F.count(F.lit(1))
    return ranked.agg((F.try_divide(2 * F.sum(F.col("i") * F.col("n")), groups * F.sum("n")) - F.try_divide(groups + 1, groups)).alias("gini"))


def rule_counts(annotated: DataFrame) -> DataFrame:
    """Rows failing each rule (not exclusive) and rows whose first failure it is."""
    failing = annotated.select(F.explode("failed").alias("rule"), "first_failed")
    return failing.groupBy("rule").agg(F.count(F.lit(1)).alias("failing"), F.count_if(F.col("rule") == F.col("first_failed")).alias("first"))


def funnel(stages: list[tuple[str, DataFrame]]) -> DataFrame:
    """Rows after each named stage and the share of the largest count; null if there are no rows."""
    out = None
    for i, (name, df) in enumerate(stages):
        row = df.agg(F.count(F.lit(1)).alias("kept")).select(F.lit(i).alias("step"), F.lit(name).alias("stage"), "kept")
        out = row if out is None else out.union(row)
    return out.withColumn("retention", F.try_divide("kept", F.max("kept").over(Window.partitionBy(F.lit(1)))))  # one row per stage


def sweep(df: DataFrame, value: str, thresholds: list[float]) -> DataFrame:
    """Rows at or above each threshold, in one pass: one counter per threshold."""
    counted = df.agg(*[F.count_if(F.col(value) >= t).alias(f"t{i}") for i, t in enumerate(thresholds)])
    pairs = ", ".join(f"cast({t} as double), t{i}" for i, t in enumerate(thresholds))
    return counted.selectExpr(f"stack({len(thresholds)}, {pairs}) as (threshold, kept)")


def agreement(scored: DataFrame, score: str, label: str, threshold: float) -> DataFrame:
    """Precision, recall, F1 at the threshold, and the rank-sum AUC with mid-ranks for ties.

    Ranks are formed over distinct scores, whose counts come from one combined aggregate, by a distributed running sum.
    A measure whose denominator is zero (no row above the threshold, one label class, an empty table) is null.
    """
    hit, true = F.col(score) >= threshold, F.col(label) == 1
    at = scored.agg(F.count_if(hit & true).alias("tp"), F.count_if(hit & ~true).alias("fp"), F.count_if(~hit & true).alias("fn"))
    by = scored.groupBy(F.col(score).alias("s")).agg(F.count_if(true).alias("pos"), F.count_if(~true).alias("neg"))
    run = relational.global_run(by, [F.col("s")], {"upto": F.col("neg")})
    auc = run.agg(F.try_divide(F.sum(F.col("pos") * (F.col("upto") - F.col("neg") / 2.0)), F.sum("pos") * F.sum("neg")).alias("auc"))
    both = at.join(F.broadcast(auc), F.lit(True))  # one row each
    p, r = F.try_divide("tp", F.col("tp") + F.col("fp")), F.try_divide("tp", F.col("tp") + F.col("fn"))
    return both.select(p.alias("precision"), r.alias("recall"), F.try_divide(2 * p * r, p + r).alias("f1"), F.round("auc", 9).alias("auc"))


def edge_accuracy(found: DataFrame, truth: DataFrame) -> DataFrame:
    """Recall and precision of an edge set against the exact one; null where there are no true or no found edges."""
    both = found.select("lo", "hi", F.lit(1).alias("f")).join(truth.select("lo", "hi", F.lit(1).alias("t")), ["lo", "hi"], "full")
    shared = F.count_if(F.col("f").isNotNull() & F.col("t").isNotNull())
    return both.agg(F.try_divide(shared, F.count("t")).alias("recall"), F.try_divide(shared, F.count("f")).alias("precision"))
