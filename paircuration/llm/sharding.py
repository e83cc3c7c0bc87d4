"""Sharding by sampled splitters: range partitions of (text hash, id) with size-weighted quantile boundaries.

Contract of `shard`: law "bytes" cuts the ordered rows where the running size passes each k/n of the total, law "rows"
where the running count does, law "key" hashes the id by a jump-consistent rule.  Equal texts are neighbours in the
order, so a group stays together unless a boundary runs through it.  Null text has size 1 and the crc of nothing; repeated
rows and rows without an id take slots of their own in an arbitrary order; an empty table gives no rows.
DataFrame functions only.
"""

from __future__ import annotations

import bisect
import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from paircuration.llm.common import settle

SAMPLES = 16_384  # bound on the sampled keys that reach the driver
ROWS_A_RANGE = 1_000_000  # there are at least 128 ranges, and more when rows would exceed this in one
_COARSE = 10  # leading bits of a key by which splitters are looked up


def _measures(df: DataFrame, id_col: str, text_col: str) -> DataFrame:
    body = F.col(text_col).cast("string")
    return df.select(
        F.col(id_col).cast("bigint").alias("row_key"),
        (F.coalesce(F.octet_length(body), F.lit(0)) + 1).cast("bigint").alias("size"),
        F.crc32(F.coalesce(body, F.lit("")).cast("binary")).alias("text_crc32"),
        F.xxhash64(body).alias("place"),
        F.xxhash64(F.coalesce(F.col(id_col).cast("bigint"), F.lit(-1)), F.lit("tie")).alias("tie"),
        F.monotonically_increasing_id().alias("grain"),  # fixed once the table is written; tells equal rows apart
    )


_KEY = ("place", "tie", "grain")


def _splitters(rows: DataFrame, total: int, ranges: int, weight: str, salt: int) -> list[tuple[int, int, int]]:
    """Quantiles of a weighted sample: a row enters with probability weight * SAMPLES / (2 * total), by its hash."""
    chance = F.least(F.lit(1.0), F.col(weight) * F.lit(SAMPLES / (2.0 * max(1, total))))
    draw = F.pmod(F.xxhash64(*_KEY, F.lit(salt)), F.lit(1 << 30)) / float(1 << 30)
    keys = sorted(tuple(r) for r in rows.filter(draw < chance).select(*_KEY).limit(SAMPLES).collect())
    return sorted({keys[i * len(keys) // ranges] for i in range(1, ranges)}) if len(keys) >= ranges else sorted(set(keys))


def _array(values) -> Column:
    return F.expr("array(" + ", ".join(f"bigint('{v}')" for v in values) + ")") if len(values) else F.expr("cast(array() as array<bigint>)")


def _in_range(bounds: list[tuple[int, int, int]]) -> Column:
    """Number of splitters at or below the row's key: a jump by the leading bits, then the few splitters that share them."""
    if not bounds:
        return F.lit(0)
    coarse = [(b[0] >> (64 - _COARSE)) + (1 << (_COARSE - 1)) for b in bounds]
    first = [bisect.bisect_left(coarse, c) for c in range((1 << _COARSE) + 1)]
    cell = (F.shiftright("place", 64 - _COARSE) + (1 << (_COARSE - 1))).cast("int")
    low, high = F.element_at(_array(first), cell + 1), F.element_at(_array(first), cell + 2)
    near = F.struct(F.col("place"), F.col("tie"), F.col("grain"))
    split = F.expr("array(" + ", ".join("struct(" + ", ".join(f"bigint('{v}')" for v in b) + ")" for b in bounds) + ")")
    own = F.slice(split, (low + 1).cast("int"), (high - low).cast("int"))
    return (low + F.size(F.filter(own, lambda x: x <= near))).cast("int")


def _ranges(rows: DataFrame, total: int, ranges: int, weight: str) -> tuple[DataFrame, list]:
    """Split into ranges; those over twice their share, their largest row apart, are subdivided by samples of themselves.

    This goes on until no range is over or none can be split further.  The totals returned are those of the last bounds.
    """
    bounds, salt = _splitters(rows, total, ranges, weight, 0), 0
    while True:
        placed = rows.withColumn("span", _in_range(bounds))
        sums = placed.groupBy("span").agg(F.sum("size"), F.count(F.lit(1)), F.sum(weight), F.max(weight)).collect()
        over = {r[0]: r[3] for r in sums if r[3] - r[4] > 2 * total / ranges}
        extra, salt = set(bounds), salt + 1
        if over:
            crowded = placed.filter(F.col("span").isin(*over))
            share = 2 * math.ceil(sum(over.values()) * ranges / max(1, total))
            extra |= set(_splitters(crowded, sum(over.values()), share, weight, salt))
        if len(extra) == len(bounds):
            return placed, sorted(sums)
        bounds = sorted(extra)


def shard(df: DataFrame, shards: int = 8, law: str = "bytes", id_col: str = "doc_id", text_col: str = "text",
          ranges: int | None = None) -> DataFrame:
    """Shard and gapless slot of every row.

    The texts stay where they are: only (id, size, crc, hash) rows are shuffled, once, by range.  Exact range totals
    give each range its offset, so the running sums are exact although the splitters are sampled.
    """
    if law == "key":
        return _by_key(df, shards, id_col, text_col)
    rows = settle(_measures(df, id_col, text_col), "measures").withColumn("one", F.lit(1))
    weight = {"bytes": "size", "rows": "one"}[law]
    total, count = rows.agg(F.coalesce(F.sum(weight), F.lit(0)), F.count(F.lit(1))).first()
    placed, sums = _ranges(rows, total, ranges or max(128, -(-count // ROWS_A_RANGE)), weight)
    spans = (sums[-1][0] + 1) if sums else 1
    before, before_rows = [0] * spans, [0] * spans
    held = {r[0]: (r[3], r[2]) for r in sums}
    for i in range(1, spans):
        more = held.get(i - 1, (0, 0))
        before[i], before_rows[i] = before[i - 1] + more[0], before_rows[i - 1] + more[1]
    order = Window.partitionBy("span").orderBy(*_KEY)
    at_span = F.col("span") + 1
    run = placed.withColumn("before", F.element_at(_array(before), at_span) + F.sum(weight).over(order.rowsBetween(Window.unboundedPreceding, 0)) - F.col(weight))
    run = run.withColumn("at", F.element_at(_array(before_rows), at_span) + F.row_number().over(order) - 1)
    run = run.withColumn("mid", F.col("before") * 2 + (F.col(weight) if law == "bytes" else F.lit(0)))
    run = settle(run.withColumn("shard", F.least(F.lit(shards - 1), F.floor(F.col("mid") * shards / F.lit(2 * max(1, total)))).cast("int")), "placed")
    first = {r[0]: r[1] for r in run.groupBy("shard").agg(F.min("at")).collect()}
    base = F.element_at(_array([first.get(i, 0) for i in range(shards)]), F.col("shard") + 1)
    return _result(run.withColumn("slot", (F.col("at") - base).cast("bigint")).withColumn("grown_shard", F.lit(None).cast("int")), law, id_col)


def _by_key(df: DataFrame, shards: int, id_col: str, text_col: str) -> DataFrame:
    """Rendezvous choice: the shard with the largest hash of (id, shard); one more shard takes rows only into itself."""
    def pick(n):
        best = F.array_max(F.array(*[F.struct(F.xxhash64(F.col("row_key"), F.lit(i)).alias("h"), F.lit(i).alias("i")) for i in range(n)]))
        return best["i"].cast("int")
    rows = settle(_measures(df, id_col, text_col).withColumn("shard", pick(shards)).withColumn("grown_shard", pick(shards + 1)), "keyed")
    spans = max(64, -(-rows.count() // ROWS_A_RANGE))
    rows = rows.withColumn("span", F.pmod(F.xxhash64("tie", "grain"), F.lit(spans)).cast("int"))
    at, starts = {}, [0] * (shards * spans)
    for s, span, n in sorted(rows.groupBy("shard", "span").agg(F.count(F.lit(1))).collect()):
        starts[s * spans + span] = at.get(s, 0)
        at[s] = at.get(s, 0) + n
    base = F.element_at(_array(starts), F.col("shard") * spans + F.col("span") + 1)
    order = Window.partitionBy("shard", "span").orderBy("row_key", "text_crc32", "grain")
    return _result(rows.withColumn("slot", (base + F.row_number().over(order) - 1).cast("bigint")), "key", id_col)


def _result(rows: DataFrame, law: str, id_col: str) -> DataFrame:
    return rows.select(F.col("row_key").alias(id_col), "size", "text_crc32", F.lit(law).alias("law"), "shard", "slot", "grown_shard")


def op5_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shard(spark.read.parquet(f"{sf_dir}/documents.parquet"), 8, "bytes")
