"""Cross-check of the banded index by the MinHash estimator of Spark ML."""

from __future__ import annotations

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from paircuration.operators import dedup
from paircuration.sources.scratch import settle


def _maps(batches):
    for batch in batches:
        for at in range(0, len(batch), 512):
            part = batch.slice(at, 512)
            sizes = pc.list_value_length(part.column(1)).to_numpy()
            maps = dedup._parity_maps(pc.list_flatten(part.column(1)).to_numpy().view("uint64"), sizes.astype("int64"))
            yield pa.record_batch([part.column(0), pa.array(sizes, pa.int32()), part.column(2), *[pa.array(maps[:, i].copy()) for i in range(dedup.MAP)]],
                                  names=["row_key", "n", "keys", *[f"b{i}" for i in range(dedup.MAP)]])


def ml_crosscheck(sets: DataFrame, id_col: str, distance: float) -> DataFrame:
    """(lo, hi, distance) pairs whose Jaccard distance is below `distance`, by ML's own index.

    The pairs are those of its `approxSimilarityJoin`: pairs that share a hash in one of the tables, measured on the hashed
    vectors.  That join moves both vectors with each pair of a bucket; here buckets meet under the bound of `dedup.bound`,
    and since a bucket of a single hash is common, only rows near in size are compared there (`dedup.bounded_meetings`).
    """
    from pyspark.ml.feature import HashingTF, MinHashLSH

    vectors = HashingTF(inputCol="tokens", outputCol="v", numFeatures=1 << 20, binary=True).transform(sets.filter(F.size("tokens") > 0))
    hashed = MinHashLSH(inputCol="v", outputCol="h", numHashTables=8, seed=7).fit(vectors).transform(vectors)
    kind, plain = sets.schema[id_col].dataType.simpleString(), F.unwrap_udt("v").getField("indices")
    keys = F.transform("h", lambda h, i: F.xxhash64(i, F.unwrap_udt(h).getField("values")[0]))
    rows = settle(hashed.select(id_col, plain.alias("tokens"), keys.alias("keys")), "hashed")
    mapped = rows.select(F.col(id_col).alias("row_key"), F.transform("tokens", lambda t: F.xxhash64(t)).alias("values"), "keys")
    bits = ", ".join(f"b{i} bigint" for i in range(dedup.MAP))
    made = settle(mapped.mapInArrow(_maps, f"row_key {kind}, n int, keys array<bigint>, {bits}").withColumnRenamed("row_key", id_col), "profiles")
    tau = 1 - distance
    pairs = settle(dedup.bounded_meetings(made, id_col, tau), "pairs")
    found = dedup.verify_grouped(pairs, rows, id_col, "exact", tau - 1e-9)
    return found.select("lo", "hi", (1 - F.col("sim")).alias("distance")).filter(F.col("distance") < distance)
