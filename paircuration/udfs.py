"""SQL names for the engine's measures, and a table function over text lines."""

from __future__ import annotations

import re

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from paircuration.config import DetectorConfig
from paircuration.operators.metrics import lcs_value

_TOKEN = re.compile("[a-z0-9_]+")


def _jaccard(a: pd.Series, b: pd.Series) -> pd.Series:
    def one(x, y):
        p, q = set(_TOKEN.findall((x or "").lower())), set(_TOKEN.findall((y or "").lower()))
        return len(p & q) / len(p | q) if p or q else 0.0
    return pd.Series([one(x, y) for x, y in zip(a, b)], dtype="float64")


def _lcs(a: pd.Series, b: pd.Series) -> pd.Series:
    def one(x, y):
        p, q = (x or "").lower().split(), (y or "").lower().split()
        n = lcs_value(p, q)
        return 2.0 * n / (len(p) + len(q)) if n else 0.0
    return pd.Series([one(x, y) for x, y in zip(a, b)], dtype="float64")


def _detector(doc: pd.Series) -> pd.Series:
    cfg = DetectorConfig()
    def one(d):
        d = d or ""
        low, lines = d.lower(), d.split("\n")
        heads = sum(bool(re.search(p, d, re.M)) for p in (r"^ *(Parameters|Args|Arguments):", r"^ *Returns?:", r"^ *(Raises|Throws):", r"^ *Examples?:"))
        first = lines[0]
        described = bool(first.strip()) and not re.match(r" *(Parameters|Args|Arguments|Returns?|Raises|Throws|Examples?):", first)
        bullets = [x for x in lines if x.startswith("- ")]
        tenths = 3 * any(p in low for p in cfg.phrases) + 2 * (len(bullets) >= 3 and len({len(x) for x in bullets}) == 1) + 2 * (heads + described >= cfg.min_sections) + any(p in low for p in cfg.generic)
        return min(10, tenths) / 10
    return pd.Series([one(d) for d in doc], dtype="float64")


class LinesOf:
    """Table function: number and text of each non-empty line."""

    def eval(self, text: str):
        for i, line in enumerate((text or "").split("\n")):
            if line:
                yield i, line


def register(spark: SparkSession) -> None:
    """token_jaccard(a, b), lcs_overlap(a, b), detector_score(doc), and the table function lines_of(text)."""
    spark.udf.register("token_jaccard", F.pandas_udf(_jaccard, T.DoubleType()))
    spark.udf.register("lcs_overlap", F.pandas_udf(_lcs, T.DoubleType()))
    spark.udf.register("detector_score", F.pandas_udf(_detector, T.DoubleType()))
    spark.udtf.register("lines_of", F.udtf(LinesOf, returnType="line_no int, line string"))
