"""Shared helpers of the training-data operators: scratch tables, crc rules and skew-safe attachment."""

from __future__ import annotations

import itertools
import os
import tempfile
import time
import uuid

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_counter = itertools.count()


def shared_dir(spark: SparkSession) -> str:
    """Folder that the driver and all executors share: spark.checkpoint.dir.

    Only a local session without that setting gets a temporary folder of its own.
    """
    conf = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if conf:
        return conf.rstrip("/")
    if not spark.sparkContext.master.startswith("local["):
        raise ValueError("spark.checkpoint.dir must name a folder shared by the driver and all executors")
    spark.conf.set("spark.checkpoint.dir", "file://" + tempfile.mkdtemp(prefix="shared-"))
    return spark.conf.get("spark.checkpoint.dir")


def scratch(spark: SparkSession, name: str) -> str:
    """A fresh path below the shared folder, grouped by application so that one delete cleans up."""
    app = spark.sparkContext.applicationId
    return f"{shared_dir(spark)}/{app}/{name}-{next(_counter)}-{os.getpid()}-{int(time.time() * 1000):x}-{uuid.uuid4().hex[:8]}"


def settle(df: DataFrame, name: str) -> DataFrame:
    """Write a narrow intermediate to the shared folder and read it back: lineage is cut, lost executors lose nothing."""
    path = scratch(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def release(spark: SparkSession) -> None:
    """Delete every scratch table of this application (call when the results have been stored)."""
    jvm = spark.sparkContext._jvm
    path = jvm.org.apache.hadoop.fs.Path(f"{shared_dir(spark)}/{spark.sparkContext.applicationId}")
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def fold_of(doc_id):
    """crc32 of the id's decimal text, modulo 3; remainder 1 is held out of every training set."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % 3


def attach(rows: DataFrame, groups: DataFrame, key: str, size: str, share: int = 1000) -> DataFrame:
    """Left-join one row per key onto many rows per key without a hot reducer.

    A key is hot when it holds at least 1/share of all rows, so there are at most `share` hot keys and their
    broadcast has a fixed bound; every other key goes through an ordinary shuffled join.  `groups` has one row per
    key and its row count in `size`; both inputs should be settled tables.  Null keys match null keys.
    """
    total = groups.agg(F.sum(size)).first()[0] or 0
    floor = max(2, -(-total // share))
    extra = [c for c in groups.columns if c != key]
    named = groups.withColumnRenamed(key, "_group_key")
    hot, cold = named.filter(F.col(size) >= floor), named.filter(F.col(size) < floor)
    on = F.col(key).eqNullSafe(F.col("_group_key"))
    few = F.broadcast(hot)
    first = rows.join(few, on, "inner").drop("_group_key")
    rest = rows.join(F.broadcast(hot.select("_group_key")), on, "left_anti").join(cold, on, "left").drop("_group_key")
    return first.select(*rows.columns, *extra).unionByName(rest.select(*rows.columns, *extra))


def pieces(texts: pa.Array, most_bytes: int = 1 << 20, most_rows: int = 512):
    """(from, to) of runs of rows with about `most_bytes` of text; a longer text is a run of its own.

    Whatever works on a run holds memory by bytes, not by rows.
    """
    sizes = pc.fill_null(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False)
    upto = np.concatenate([[0], np.cumsum(sizes, dtype=np.int64)])
    at = 0
    while at < len(texts):
        to = int(np.searchsorted(upto, upto[at] + most_bytes, side="right")) - 1
        to = min(max(to, at + 1), at + most_rows, len(texts))
        yield at, to
        at = to


def sigmoid(x):
    return 1.0 / (1.0 + np.exp(-np.clip(x, -40, 40)))


def fit_logistic(x: np.ndarray, y: np.ndarray, weight: np.ndarray | None = None, l2: float = 1.0, rounds: int = 50) -> np.ndarray:
    """Weighted ridge logistic regression by Newton steps; the last coefficient is the unpenalised intercept."""
    x = np.hstack([x, np.ones((len(x), 1))])
    weight = np.ones(len(x)) if weight is None else weight
    ridge = np.full(x.shape[1], l2)
    ridge[-1] = 1e-6
    beta = np.zeros(x.shape[1])
    for _ in range(rounds):
        p = sigmoid(x @ beta)
        grad = x.T @ (weight * (p - y)) + ridge * beta
        hess = (x * (weight * p * (1 - p))[:, None]).T @ x + np.diag(ridge)
        step = np.linalg.solve(hess, grad)
        beta -= step * min(1.0, 5.0 / max(1e-9, np.abs(step).max()))
        if np.abs(step).max() < 1e-7:
            break
    return beta
