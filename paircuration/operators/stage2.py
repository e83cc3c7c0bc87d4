"""Quality score: eight weighted dimensions on a 0..10 scale."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from paircuration.config import DIMENSIONS, Stage2Config
from paircuration.functions import rules as R
from paircuration.functions.dialect import SPARK

TEXT_DIMENSIONS = ("clarity", "structure", "completeness")


def dimensions(df: DataFrame, names: tuple[str, ...] = DIMENSIONS) -> DataFrame:
    """Adds struct q of the dimension scores, each computed once per row."""
    text = R.dimensions(SPARK)
    return df.withColumn("q", F.struct(*[F.expr(text[n]).cast("double").alias(n) for n in names]))


def score(df: DataFrame, cfg: Stage2Config = Stage2Config(), available: tuple[str, ...] = DIMENSIONS) -> DataFrame:
    """Adds quality; dimensions that a carrier lacks are left out of numerator and denominator, or count zero."""
    text = R.quality(SPARK, cfg, available)
    for n in available:
        text = text.replace(f"cast({n} as", f"cast(q.{n} as")
    return df.withColumn("quality", F.expr(text))


def retain(df: DataFrame, cfg: Stage2Config = Stage2Config()) -> DataFrame:
    return df.filter(F.col("quality") >= cfg.min_score)
