"""Readers and writers: Parquet tables, JSON lines, CSV, text lines, partitioned and bucketed tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def load(spark: SparkSession, sf_dir: str, table: str, columns: list[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{table}.parquet")
    return df.select(*columns) if columns else df


def run_sql(spark: SparkSession, sql: str, **frames: DataFrame) -> DataFrame:
    """SQL text over DataFrames: `@name@` stands for the frame of that name; braces are ordinary characters."""
    sql = sql.replace("{", "{{").replace("}", "}}")
    for name in frames:
        sql = sql.replace(f"@{name}@", "{" + name + "}")
    return spark.sql(sql, **frames)


def as_timestamp(df: DataFrame, *columns: str) -> DataFrame:
    """Zone-less timestamps as session-zone timestamps: watermarks and windows need those."""
    return df.withColumns({c: F.col(c).cast("timestamp") for c in columns})


def write_jsonl(df: DataFrame, path: str) -> None:
    df.write.mode("overwrite").json(path)


def write_partitioned(df: DataFrame, path: str, by: str) -> None:
    """One folder per value; rows are dealt by value and a salt, so a hot value does not end in one task."""
    salt = F.pmod(F.xxhash64(*df.columns), F.lit(8))
    df.repartition(by, salt).write.mode("overwrite").partitionBy(by).parquet(path)


def write_bucketed(df: DataFrame, table: str, key: str, buckets: int) -> None:
    df.write.mode("overwrite").format("parquet").bucketBy(buckets, key).sortBy(key).saveAsTable(table)


def write_pairs(df: DataFrame, path: str, fmt: str = "parquet") -> None:
    """Prompt and target columns for training."""
    getattr(df.select(F.col("code").alias("prompt"), F.col("doc").alias("target"), *[c for c in df.columns if c not in ("code", "doc")]).write.mode("overwrite"), fmt)(path)
