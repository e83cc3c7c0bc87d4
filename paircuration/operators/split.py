"""Train, validation and test splits; truncation, packing and the step plan."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from paircuration.config import TrainingConfig

NAMES = ("train", "validation", "test")


def stratified(df: DataFrame, by: str, id_col: str, cfg: TrainingConfig = TrainingConfig()) -> DataFrame:
    """Exact shares per stratum: rank by a seeded digest, cut at the floor of each cumulative share.

    Ranks come in two levels so that one large stratum is not one task: digests are dealt over 256 ranges by their first
    byte, counted, and ranked inside each range on top of the ranges before it.
    """
    a, b = cfg.split[0], cfg.split[0] + cfg.split[1]
    keyed = df.withColumn("_h", F.md5(F.concat(F.lit(f"{cfg.seed}:"), F.col(id_col).cast("string")))).withColumn("_range", F.substring("_h", 1, 2))
    counts = keyed.groupBy(by, "_range").agg(F.count(F.lit(1)).alias("_n"))
    before = Window.partitionBy(by).orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.withColumn("_before", F.coalesce(F.sum("_n").over(before), F.lit(0))).withColumn("_total", F.sum("_n").over(Window.partitionBy(by))).drop("_n")
    ranked = keyed.join(offsets, [by, "_range"]).withColumn("_rank", F.col("_before") + F.row_number().over(Window.partitionBy(by, "_range").orderBy("_h", id_col)))
    name = F.when(F.col("_rank") <= F.floor(F.col("_total") * F.lit(a)), NAMES[0]).when(F.col("_rank") <= F.floor(F.col("_total") * F.lit(b)), NAMES[1]).otherwise(NAMES[2])
    return ranked.withColumn("split", name).drop("_h", "_range", "_before", "_total", "_rank")


def first_rows(df: DataFrame, digest: Column, n: int) -> DataFrame:
    """The n rows with the smallest hex digests (all, if there are fewer); digests are taken to be distinct.

    Rows are counted by the first four digits, so only those of one such range are ever sorted.
    """
    keyed = df.withColumn("_h", digest).withColumn("_range", F.substring("_h", 1, 4))
    counts, cut, left = keyed.groupBy("_range").agg(F.count(F.lit(1)).alias("n")).orderBy("_range").collect(), None, n  # at most 65,536 rows
    for r in counts:
        if r["n"] > left:
            cut = r["_range"]
            break
        left -= r["n"]
    if cut is None:
        return df
    last = keyed.filter(F.col("_range") == cut).orderBy("_h").limit(left)
    return keyed.filter(F.col("_range") < cut).union(last).drop("_h", "_range")


def hashed(df: DataFrame, id_col: str, cfg: TrainingConfig = TrainingConfig()) -> DataFrame:
    """Shares in expectation, without any shuffle: for streams and very large tables."""
    bucket = F.conv(F.substring(F.md5(F.concat(F.lit(f"{cfg.seed}:"), F.col(id_col).cast("string"))), 1, 8), 16, 10).cast("bigint") % 1000
    a, b = int(1000 * cfg.split[0]), int(1000 * (cfg.split[0] + cfg.split[1]))
    return df.withColumn("split", F.when(bucket < a, NAMES[0]).when(bucket < b, NAMES[1]).otherwise(NAMES[2]))


def leakage_safe(df: DataFrame, clusters: DataFrame, id_col: str, cfg: TrainingConfig = TrainingConfig()) -> DataFrame:
    """All members of a near-duplicate cluster share a split: the cluster id is hashed. `clusters` is (id, root)."""
    joined = df.join(clusters.select(F.col("id").alias(id_col), "root"), id_col, "left").withColumn("_cluster", F.coalesce("root", id_col)).drop("root")
    return hashed(joined, "_cluster", cfg).drop("_cluster")


def truncate(text, max_tokens: int = 2048):
    """Array of the first white-space tokens."""
    return F.slice(F.split(F.trim(F.regexp_replace(text, r"\s+", " ")), " "), 1, max_tokens)


def running_pack(df: DataFrame, shard_col: str, order_col: str, tokens_col: str, max_len: int) -> DataFrame:
    """Concatenate each shard's tokens in order and cut every max_len: adds the first chunk and the offset in it."""
    run = Window.partitionBy(shard_col).orderBy(order_col).rowsBetween(Window.unboundedPreceding, 0)
    begin = F.sum(tokens_col).over(run) - F.col(tokens_col)
    return df.withColumn("begin", begin).withColumn("chunk", F.floor(F.col("begin") / max_len)).withColumn("offset", F.col("begin") % max_len)


def pack(df: DataFrame, id_col: str, tokens_col: str, max_len: int, method: str = "next_fit") -> DataFrame:
    """(id, partition-local sequence, tokens) per row, inside each partition, streaming.

    next_fit keeps the order; first_fit_decreasing packs each Arrow batch tighter.  A row longer than max_len is cut.
    """
    def next_fit(sizes):
        bins, held, k = np.empty(len(sizes), np.int64), 0, 0
        for i, n in enumerate(sizes):
            if held and held + n > max_len:
                k, held = k + 1, 0
            bins[i], held = k, held + n
        return bins

    def decreasing(sizes):
        bins, room = np.empty(len(sizes), np.int64), []
        for i in np.argsort(-sizes, kind="stable"):
            k = next((j for j, r in enumerate(room) if r >= sizes[i]), None)
            if k is None:
                room.append(max_len)
                k = len(room) - 1
            room[k] -= sizes[i]
            bins[i] = k
        return bins

    fit = {"next_fit": next_fit, "first_fit_decreasing": decreasing}[method]

    def run(batches):
        base = 0
        for batch in batches:
            sizes = np.minimum(batch.column(1).to_numpy(zero_copy_only=False), max_len)
            bins = fit(sizes)
            yield pa.record_batch([batch.column(0), pa.array(base + bins), pa.array(sizes)], names=["row_key", "sequence", "tokens"])
            base += int(bins.max()) + 1 if len(bins) else 0

    kind = df.schema[id_col].dataType.simpleString()
    return df.select(F.col(id_col).alias("row_key"), F.col(tokens_col).cast("bigint").alias("n")).mapInArrow(run, f"row_key {kind}, sequence bigint, tokens bigint").withColumnRenamed("row_key", id_col)


def step_plan(spark: SparkSession, examples: int, cfg: TrainingConfig = TrainingConfig()) -> DataFrame:
    """(step, epoch, rate): linear warm-up, then linear decay to zero."""
    batch = cfg.per_device_batch * cfg.accumulation
    per_epoch = -(-examples // batch)
    total = per_epoch * cfg.epochs
    step = F.col("id") + 1
    rate = F.when(step <= cfg.warmup_steps, step / cfg.warmup_steps).otherwise((total - step) / max(1, total - cfg.warmup_steps)) * cfg.peak_rate
    return spark.range(total).select(step.alias("step"), (F.floor(F.col("id") / per_epoch) + 1).alias("epoch"), F.round(rate, 12).alias("rate"))
