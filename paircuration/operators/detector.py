"""Machine-written documentation: additive capped rule score, marked or dropped."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from paircuration.config import DetectorConfig
from paircuration.functions import rules as R
from paircuration.functions.dialect import SPARK

_custom: dict[str, tuple[Callable[[], Column], int]] = {}


def register(name: str, condition: Callable[[], Column], tenths: int) -> None:
    """Add a heuristic of one's own: a condition over the pair columns and its increment in tenths."""
    _custom[name] = (condition, tenths)


def unregister(name: str) -> None:
    _custom.pop(name, None)


def signals(df: DataFrame, cfg: DetectorConfig = DetectorConfig()) -> DataFrame:
    return df.withColumns({k: F.expr(v) for k, v in R.detector(SPARK, cfg).items()})


def score(df: DataFrame, cfg: DetectorConfig = DetectorConfig()) -> DataFrame:
    """Adds ai_score decimal(3,1), ai_matched (comma-joined names) and ai_flag; tenths are integers, so ties are exact."""
    df = signals(df, cfg)
    tenths, names = F.expr(R.detector_tenths(SPARK, cfg)), F.expr(R.matched(SPARK, cfg))
    for name, (condition, extra) in _custom.items():
        hit = F.coalesce(condition(), F.lit(False))
        tenths = F.least(F.lit(10), tenths + F.when(hit, extra).otherwise(0))
        names = F.concat_ws(",", F.when(names != "", names), F.when(hit, F.lit(name)))
    df = df.withColumn("ai_tenths", tenths.cast("int")).withColumn("ai_matched", names)
    return df.withColumn("ai_score", (F.col("ai_tenths") / 10).cast("decimal(3,1)")).withColumn("ai_flag", F.col("ai_tenths") >= cfg.tau_ai_tenths)


def policy(df: DataFrame, cfg: DetectorConfig = DetectorConfig()) -> DataFrame:
    return df.filter(~F.col("ai_flag")) if cfg.policy == "drop" else df


def repeated_structure(df: DataFrame, share: float = 0.5, least: int = 5) -> DataFrame:
    """Corpus variant of the structure signal: the row's order of sections is the repo's habit.

    One map-side combined aggregate per (repo, order); the joined side has one row per order and repo.
    """
    places = [F.instr("doc", head) for head in ("Parameters:", "Returns:", "Raises:", "Examples:")]
    order = F.concat_ws(">", *[F.when(p > 0, F.lit(str(i))) for i, p in enumerate(places)])
    marked = df.withColumn("section_order", order)
    counts = marked.groupBy("repo", "section_order").count()
    habit = counts.withColumn("total", F.sum("count").over(Window.partitionBy("repo")))
    habit = habit.filter((F.col("count") >= share * F.col("total")) & (F.col("count") >= least) & (F.col("section_order") != "")).select("repo", "section_order", F.lit(True).alias("is_habit"))
    return marked.join(habit, ["repo", "section_order"], "left").withColumn("repeated_structure", F.coalesce("is_habit", F.lit(False))).drop("is_habit")
