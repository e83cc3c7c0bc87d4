"""Overlap of generated and reference texts: n-gram precision with brevity penalty, and LCS overlap."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


def tokens(text: Column, limit: int | None = None) -> Column:
    """Tokens of the whole text, or the first `limit`."""
    found = F.filter(F.split(F.lower(text), "[ \n\t]+"), lambda t: t != "")
    return found if limit is None else F.slice(found, 1, limit)


def _grams(df: DataFrame, id_col: str, column: str, max_n: int) -> DataFrame:
    """(id, n, gram, times)"""
    size = F.size(column)

    def order(n):
        return F.transform(F.sequence(F.lit(1), F.greatest(size - n + 1, F.lit(1))), lambda i: F.struct(
            F.lit(n).alias("n"), F.array_join(F.slice(column, i, n), " ").alias("gram"), (i + n - 1 <= size).alias("whole")))

    orders = [order(n) for n in range(1, max_n + 1)]
    flat = df.select(id_col, F.explode(F.concat(*orders)).alias("g")).filter("g.whole")
    return flat.groupBy(id_col, F.col("g.n").alias("n"), F.col("g.gram").alias("gram")).agg(F.count(F.lit(1)).alias("times"))


def clipped(df: DataFrame, id_col: str, max_n: int = 4) -> DataFrame:
    """(id, n, matched, total) for n in 1..max_n; `df` has token arrays cand and ref. Both sides group by the same key."""
    cand = _grams(df, id_col, "cand", max_n)
    ref = _grams(df, id_col, "ref", max_n).withColumnRenamed("times", "ref_times")
    met = cand.join(ref, [id_col, "n", "gram"], "left")
    return met.groupBy(id_col, "n").agg(F.sum(F.least("times", F.coalesce("ref_times", F.lit(0)))).alias("matched"), F.sum("times").alias("total"))


def _combine(matched: list[Column], total: list[Column], c: Column, r: Column, smooth: str) -> Column:
    logs = []
    for i, (m, t) in enumerate(zip(matched, total)):
        m, t = F.coalesce(m, F.lit(0)).cast("double"), F.coalesce(t, F.lit(0)).cast("double")
        if smooth == "add1" and i > 0:
            m, t = m + 1, t + 1
        if smooth == "eps":
            m = F.when(m == 0, 0.1).otherwise(m)
        logs.append(F.when((m > 0) & (t > 0), F.log(m / t)))
    mean = sum(logs[1:], logs[0]) / len(logs)
    penalty = F.when(c >= r, 1.0).when(c == 0, 0.0).otherwise(F.exp(1 - r / c))
    return F.coalesce(penalty * F.exp(mean), F.lit(0.0))


def bleu(df: DataFrame, id_col: str, max_n: int = 4, smooth: str = "none") -> DataFrame:
    """(id, bleu): sentence level; smooth none, add1 (orders above one) or eps."""
    parts = clipped(df, id_col, max_n)
    wide = parts.groupBy(id_col).agg(*[F.sum(F.when(F.col("n") == n, F.col(k))).alias(f"{k}{n}") for n in range(1, max_n + 1) for k in ("matched", "total")])
    sized = df.select(id_col, F.size("cand").alias("c"), F.size("ref").alias("r")).join(wide, id_col, "left")
    cols = range(1, max_n + 1)
    return sized.select(id_col, _combine([F.col(f"matched{n}") for n in cols], [F.col(f"total{n}") for n in cols], F.col("c"), F.col("r"), smooth).alias("bleu"))


def bleu_corpus(df: DataFrame, id_col: str, max_n: int = 4) -> DataFrame:
    """One row: counts are summed before the mean."""
    parts = clipped(df, id_col, max_n).agg(*[F.sum(F.when(F.col("n") == n, F.col(k))).alias(f"{k}{n}") for n in range(1, max_n + 1) for k in ("matched", "total")])
    sizes = df.agg(F.sum(F.size("cand")).alias("c"), F.sum(F.size("ref")).alias("r"))
    cols = range(1, max_n + 1)
    both = parts.withColumn("_one", F.lit(1)).join(sizes.withColumn("_one", F.lit(1)), "_one")
    return both.select(_combine([F.col(f"matched{n}") for n in cols], [F.col(f"total{n}") for n in cols], F.col("c"), F.col("r"), "none").alias("bleu"))


def lcs_length(a: Column, b: Column) -> Column:
    """Longest common subsequence of two arrays: a dynamic-programming row folded over a, inside Catalyst."""
    start = F.transform(b, lambda _: F.lit(0))

    def row(prev, x):
        cells = F.arrays_zip(b.alias("t"), prev.alias("up"), F.slice(F.concat(F.array(F.lit(0)), prev), F.lit(1), F.size(b)).alias("diag"))
        first = F.struct(F.lit(0).alias("left"), F.slice(prev, 1, 0).alias("out"))

        def cell(s, c):
            best = F.when(c["t"] == x, c["diag"] + 1).otherwise(F.greatest(c["up"], s["left"]))
            return F.struct(best.alias("left"), F.concat(s["out"], F.array(best)).alias("out"))

        return F.aggregate(cells, first, cell, lambda s: s["out"])

    return F.when((F.size(a) == 0) | (F.size(b) == 0), 0).otherwise(F.element_at(F.aggregate(a, start, row), -1))


def lcs_value(a, b) -> int:
    """Bit-parallel LCS length of two token sequences."""
    places: dict[str, int] = {}
    for i, t in enumerate(a):
        places[t] = places.get(t, 0) | 1 << i
    row = 0
    for t in b:
        x = places.get(t, 0) | row
        row = x & ~(x - ((row << 1) | 1)) if x else row
    return bin(row).count("1")


@F.pandas_udf(T.IntegerType())
def lcs_length_arrow(a: pd.Series, b: pd.Series) -> pd.Series:
    """The same by big-integer bit vectors, for long texts."""
    return pd.Series([0 if x is None or y is None else lcs_value(x, y) for x, y in zip(a, b)], dtype=np.int32)


def lcs_overlap(df: DataFrame, cand: str = "cand", ref: str = "ref", beta: float = 1.0, arrow: bool = True) -> DataFrame:
    """Adds lcs, precision, recall and lcs_f."""
    df = df.withColumn("lcs", lcs_length_arrow(cand, ref) if arrow else lcs_length(F.col(cand), F.col(ref)))
    p = F.when(F.size(cand) > 0, F.col("lcs") / F.size(cand)).otherwise(0.0)
    r = F.when(F.size(ref) > 0, F.col("lcs") / F.size(ref)).otherwise(0.0)
    df = df.withColumn("precision", p).withColumn("recall", r)
    b2 = beta * beta
    f = (1 + b2) * F.col("precision") * F.col("recall") / (F.col("recall") + b2 * F.col("precision"))
    return df.withColumn("lcs_f", F.when(F.col("lcs") > 0, f).otherwise(0.0))


def report(scores: DataFrame, by: str, measures: list[str]) -> DataFrame:
    """Mean per stratum, plus the macro mean of those and the micro mean of all rows."""
    strata = scores.groupBy(by).agg(F.count(F.lit(1)).alias("n"), *[F.avg(m).alias(m) for m in measures])
    macro = strata.agg(F.sum("n").alias("n"), *[F.avg(m).alias(m) for m in measures]).select(F.lit("(macro)").alias(by), "n", *measures)
    micro = scores.agg(F.count(F.lit(1)).alias("n"), *[F.avg(m).alias(m) for m in measures]).select(F.lit("(micro)").alias(by), "n", *measures)
    return strata.unionByName(macro).unionByName(micro)


def relative_gain(old: Column, new: Column) -> Column:
    """Null where the old value is zero."""
    return F.try_divide(new - old, old)
