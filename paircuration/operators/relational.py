"""Joins, rankings and samples that Spark has no single operator for, as compositions of DataFrame operators."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def salted_join(rows: DataFrame, side: DataFrame, key: str, salts: int) -> DataFrame:
    """Inner join with a hot key spread over `salts` reducers; the side (one row per key) is repeated that often."""
    left = rows.withColumn("_salt", F.pmod(F.xxhash64(*rows.columns), F.lit(salts)).cast("int"))
    right = side.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return left.join(right, [key, "_salt"]).drop("_salt")


def range_join(points: DataFrame, ranges: DataFrame, value: str, low: str, high: str, width: int) -> DataFrame:
    """value BETWEEN low AND high by equal-width cells: an equi-join on the cell, then the exact test."""
    cells = ranges.withColumn("_cell", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width))))
    return points.withColumn("_cell", F.floor(F.col(value) / width)).join(cells, "_cell").filter(F.col(value).between(F.col(low), F.col(high))).drop("_cell")


def interval_join(left: DataFrame, right: DataFrame, key: str, ts: str, seconds: int) -> DataFrame:
    """Pairs of one key with 0 < right.ts - left.ts <= seconds, aliased l and r: cells of that width, two for each left row."""
    cell = F.floor(F.unix_micros(ts) / (seconds * 1_000_000))
    a = left.withColumn("_cell", F.explode(F.array(cell, cell + 1))).alias("l")
    b = right.withColumn("_cell", cell).alias("r")
    near = (F.col(f"l.{key}") == F.col(f"r.{key}")) & (F.col("l._cell") == F.col("r._cell"))
    gap = F.unix_micros(F.col(f"r.{ts}")) - F.unix_micros(F.col(f"l.{ts}"))
    return a.join(b, near).filter((gap > 0) & (gap <= seconds * 1_000_000))


def asof_join(left: DataFrame, right: DataFrame, key: str, ts: str, value: str) -> DataFrame:
    """Each left row with `found`, the value of the latest right row of its key at or before it (ties: largest value).

    Both sides are interleaved and carried forward by one window: no pairs are formed.
    """
    a = left.withColumn("_side", F.lit(1)).withColumn("_value", F.lit(None).cast(right.schema[value].dataType))
    b = right.select(*[F.col(c) if c in (key, ts) else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns], F.lit(0).alias("_side"), F.col(value).alias("_value"))
    run = Window.partitionBy(key).orderBy(ts, "_side", "_value").rowsBetween(Window.unboundedPreceding, 0)
    return a.unionByName(b).withColumn("found", F.last("_value", ignorenulls=True).over(run)).filter("_side = 1").drop("_side", "_value")


def bucket_pairs(df: DataFrame, bucket: list[str], id_col: str) -> DataFrame:
    """(lo, hi) neighbours by id inside each bucket: n - 1 links connect a bucket of n rows, none expands into all pairs."""
    before = F.lag(id_col).over(Window.partitionBy(*bucket).orderBy(id_col))
    return df.withColumn("lo", before).filter("lo IS NOT NULL").select("lo", F.col(id_col).alias("hi"))


def top_k(df: DataFrame, by: list[str], order: list[Column], k: int) -> DataFrame:
    """First k rows of each group; Catalyst turns the rank filter into a group limit before the shuffle."""
    return df.withColumn("_rn", F.row_number().over(Window.partitionBy(*by).orderBy(*order))).filter(F.col("_rn") <= k).drop("_rn")


def global_run(df: DataFrame, order: list[Column], sums: dict[str, Column]) -> DataFrame:
    """Running sums over the whole table, the row itself included, without a single-task window.

    Range partitions are settled, their totals give each its offset, and windows run inside them.  Rows must be told
    apart by the order, or equal rows share an arbitrary order among themselves.
    """
    from paircuration.sources.scratch import settle

    parts = df
    for name, value in sums.items():
        parts = parts.withColumn(f"_{name}", value)
    parts = settle(parts.repartitionByRange(*order).withColumn("_part", F.spark_partition_id()), "ranges")
    totals = parts.groupBy("_part").agg(*[F.sum(f"_{n}").alias(f"_t{n}") for n in sums])
    earlier = Window.partitionBy(F.lit(0)).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)  # one row per partition
    before = totals.select("_part", *[F.coalesce(F.sum(f"_t{n}").over(earlier), F.lit(0)).alias(f"_b{n}") for n in sums])
    local = Window.partitionBy("_part").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    run = parts.join(F.broadcast(before), "_part")  # as many rows as there are partitions
    return run.select(*df.columns, *[(F.col(f"_b{n}") + F.sum(f"_{n}").over(local)).alias(n) for n in sums])


def global_rank(df: DataFrame, order: list[Column], name: str) -> DataFrame:
    """Gapless rank from 0 over the whole table."""
    return global_run(df, order, {name: F.lit(1)}).withColumn(name, F.col(name) - 1)


def hash_sample(df: DataFrame, key: str, seed: str, one_in: int) -> DataFrame:
    """Rows whose seeded digest falls in one of `one_in` buckets: repeatable, and no shuffle."""
    bucket = F.conv(F.substring(F.md5(F.concat(F.lit(seed), F.col(key).cast("string"))), 1, 4), 16, 10).cast("int") % one_in
    return df.filter(bucket == 0)
