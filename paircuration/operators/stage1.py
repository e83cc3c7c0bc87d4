"""Basic filter: named threshold rules, narrow and without any shuffle."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from paircuration.config import Stage1Config
from paircuration.functions import rules as R
from paircuration.functions.dialect import SPARK


def rules(cfg: Stage1Config = Stage1Config()) -> dict[str, Column]:
    """rule name -> Column that is true when a row fails it."""
    return {name: F.expr(text) for name, text in R.stage1(SPARK, cfg).items()}


def apply(df: DataFrame, cfg: Stage1Config = Stage1Config(), mode: str = "drop") -> DataFrame:
    """"drop" keeps passing rows; "annotate" adds failed (all rules) and first_failed (in rule order)."""
    fails = rules(cfg)
    if mode == "drop":
        for fail in fails.values():  # cheap length rules come first
            df = df.filter(~fail)
        return df
    names = F.array(*[F.when(fail, F.lit(name)) for name, fail in fails.items()])
    return df.withColumn("failed", F.array_compact(names)).withColumn("first_failed", F.try_element_at("failed", F.lit(1)))
