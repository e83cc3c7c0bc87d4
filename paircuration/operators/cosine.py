"""All pairs of vectors that reach a cosine, joined exactly in blocks."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def neighbours(df: DataFrame, id_col: str, vector: str, least: float, block: int = 2048) -> DataFrame:
    """(lo, hi, cosine) of all pairs of ids lo < hi with equally long vectors that reach the cosine.

    Vectors of one size are dealt by hash into blocks of about `block`, and every two blocks meet in one matrix product.
    The work is that of all pairs, so no pair is missed. Null and zero vectors and rows without an id have no neighbours.
    """
    rows = df.select(F.col(id_col).cast("bigint").alias("id"), F.col(vector).cast("array<double>").alias("vec")).filter("id IS NOT NULL AND size(vec) > 0")
    rows = rows.withColumn("size", F.size("vec"))
    counts = rows.groupBy("size").agg(F.ceil(F.count(F.lit(1)) / block).cast("int").alias("blocks"))
    placed = rows.join(counts, "size").withColumn("block", F.pmod(F.xxhash64("id", "vec"), "blocks").cast("int"))
    sent = placed.select("size", "id", "vec", "block", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other"))
    sent = sent.select("size", F.least("block", "other").alias("first"), F.greatest("block", "other").alias("second"), "block", "id", "vec")

    def meet(table):
        vec = table["vec"].combine_chunks()
        x = vec.flatten().to_numpy(zero_copy_only=False).reshape(len(table), -1)
        norm = np.linalg.norm(x, axis=1)
        good = norm > 0
        x, ids = x[good] / norm[good, None], table["id"].to_numpy()[good]
        first, second = table["first"][0].as_py(), table["second"][0].as_py()
        left = table["block"].to_numpy()[good] == first
        right = left if first == second else ~left
        (xa, a), (xb, b) = (x[left], ids[left]), (x[right], ids[right])
        found = []
        for at in range(0, len(a), 1024):
            cosine = xa[at : at + 1024] @ xb.T
            i, j = np.nonzero(cosine >= least)
            keep = a[at + i] != b[j] if first != second else (at + i < j) & (a[at + i] != b[j])
            i, j = i[keep], j[keep]
            found.append((np.minimum(a[at + i], b[j]), np.maximum(a[at + i], b[j]), cosine[i, j]))
        lo, hi, cosine = (np.concatenate(c) for c in zip(*found)) if found else (np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0))
        return pa.table({"lo": pa.array(lo, pa.int64()), "hi": pa.array(hi, pa.int64()), "cosine": pa.array(cosine, pa.float64())})

    return sent.groupBy("size", "first", "second").applyInArrow(meet, "lo bigint, hi bigint, cosine double")
