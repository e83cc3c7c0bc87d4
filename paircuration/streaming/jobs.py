"""Structured Streaming jobs over event and document files; each has a batch twin as its oracle.

Every job reads files, keeps its checkpoint in the shared folder, runs what is available, and stores its result as
Parquet, so nothing is gathered in the driver.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import replace

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from paircuration.config import DedupConfig
from paircuration.operators import dedup, greedy
from paircuration.sources.scratch import fresh, settle
from paircuration.sources.tables import as_timestamp, load


def source(spark: SparkSession, sf_dir: str, table: str, per_trigger: int = 1) -> DataFrame:
    """A table's files as a stream; zone-less event time becomes a timestamp, as watermarks need."""
    schema = load(spark, sf_dir, table).schema
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).parquet(f"{sf_dir}/{table}.parquet*")
    return as_timestamp(stream, "ts") if "ts" in stream.columns else stream


def run_append(stream: DataFrame, name: str) -> DataFrame:
    """Append-mode file sink; returns what it stored."""
    spark, path = stream.sparkSession, fresh(stream.sparkSession, name)
    job = stream.writeStream.outputMode("append").format("parquet").option("checkpointLocation", f"{path}-state").trigger(availableNow=True).start(path)
    job.awaitTermination()
    return spark.read.schema(stream.schema).parquet(path)


def run_complete(stream: DataFrame, name: str) -> DataFrame:
    """Complete mode: every trigger replaces the stored result, so a repeated batch changes nothing."""
    path = fresh(stream.sparkSession, name)
    return _each(stream, path, "complete", lambda df, _: df.write.mode("overwrite").parquet(path))


def _each(stream: DataFrame, path: str, mode: str, sink: Callable[[DataFrame, int], None]) -> DataFrame:
    job = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{path}-state").foreachBatch(sink).trigger(availableNow=True).start()
    job.awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(path)


def windowed(events: DataFrame, window) -> DataFrame:
    grouped = events.withWatermark("ts", "10 minutes").groupBy(window.alias("w"), "event_type")
    return grouped.agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 6).alias("total"))


def flat(df: DataFrame) -> DataFrame:
    ends = {"start": F.col("w.start").cast("timestamp_ntz"), "end": F.col("w.end").cast("timestamp_ntz")}
    return df.select(ends["start"].alias("start"), ends["end"].alias("end"), *[c for c in df.columns if c != "w"])


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    grouped = events.withWatermark("ts", "10 minutes").groupBy(F.session_window("ts", gap).alias("w"), "user_id")
    return grouped.agg(F.count(F.lit(1)).alias("n"))


def running_totals(events: DataFrame) -> DataFrame:
    """(user_id, n, total) after each trigger, by arbitrary state per user."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, total = state.get if state.exists else (0, 0.0)
        for pdf in frames:
            n, total = n + len(pdf), total + float(pdf["value"].sum())
        state.update((n, total))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "total": [round(total, 6)]})

    return events.select("user_id", "value").groupBy("user_id").applyInPandasWithState(
        step, "user_id bigint, n bigint, total double", "n bigint, total double", "update", GroupStateTimeout.NoTimeout)


class NearDedupStream:
    """Incremental near-duplicate removal: each batch meets the index of kept rows, then the ordered pass inside itself.

    The index lies below one folder: for each batch number the kept rows and their profiles with their band keys.  A finished part has a
    marker, and parts are listed from the folder, so a job that starts again there knows all earlier batches; a batch that
    is run again replaces its own part.  Rows of later batches must follow in the order.
    """

    def __init__(self, spark: SparkSession, cfg: DedupConfig = DedupConfig(), folder: str | None = None):
        self.spark, self.cfg, self.folder = spark, replace(cfg, verify="exact"), (folder or fresh(spark, "near-index")).rstrip("/")

    @property
    def parts(self) -> list[int]:
        """Numbers of the finished batches."""
        path = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{self.folder}/index")
        files = path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration())
        if not files.exists(path):
            return []
        done = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path
        return sorted(int(x.getPath().getName()) for x in files.listStatus(path) if files.exists(done(x.getPath(), "_SUCCESS")))

    def _read(self, kind: str, before: int) -> DataFrame | None:
        paths = [f"{self.folder}/{kind}/{b}" for b in self.parts if b < before]
        return self.spark.read.parquet(*paths) if paths else None

    def step(self, batch: DataFrame, number: int, id_col: str = "doc_id") -> DataFrame:
        """Kept rows of the batch, also stored. Rows of later batches must follow in the order.

        Pairs that only share a bucket make no row (`dedup.bound`), and one verification by groups serves both the pairs with
        kept rows and those inside the batch.
        """
        rows = settle(batch.select(id_col, dedup.token_set(F.col("text")).alias("tokens")), "batch")
        made = settle(dedup.profiles(rows.select(id_col, F.array_join("tokens", " ").alias("text")), id_col, F.col("text"), self.cfg), "profiles")
        inner = settle(dedup.bounded_index(made, id_col), "bands")
        pairs, features = dedup.bounded_candidates(inner, inner, id_col, self.cfg), rows
        old, old_rows = self._read("index", number), self._read("rows", number)
        if old is not None:
            old_keys, new_keys = (x.select(F.explode("keys").alias("key")).distinct() for x in (old, made))
            both = settle(new_keys.join(old_keys, "key", "left_semi"), "shared")
            known, asked = (settle(dedup.bounded_index(x, id_col, both), "bands") for x in (old, made))
            pairs, features = pairs.union(dedup.bounded_candidates(known, asked, id_col, self.cfg, ordered=False)), rows.union(old_rows)
        edges = settle(dedup.verify_grouped(settle(pairs, "pairs"), features, id_col, "exact", self.cfg.tau_lsh), "edges")
        mine = lambda c: rows.select(F.col(id_col).alias(c))
        gone = settle(edges.join(mine("lo"), "lo", "left_anti").select(F.col("hi").alias("id")).distinct(), "gone")
        inside = edges.join(mine("lo"), "lo", "left_semi")
        for c in ("lo", "hi"):
            inside = inside.join(gone.select(F.col("id").alias(c)), c, "left_anti")
        dropped = settle(greedy.resolve(inside.select("lo", "hi")).filter("NOT kept").select("id").union(gone), "dropped").withColumnRenamed("id", id_col)
        rows.join(dropped, id_col, "left_anti").write.mode("overwrite").parquet(f"{self.folder}/rows/{number}")
        made.join(dropped, id_col, "left_anti").write.mode("overwrite").parquet(f"{self.folder}/index/{number}")
        return self.spark.read.schema(rows.schema).parquet(f"{self.folder}/rows/{number}")

    def kept(self) -> DataFrame:
        return self.spark.read.parquet(*[f"{self.folder}/rows/{b}" for b in self.parts])
