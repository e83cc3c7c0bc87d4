"""Exact deduplication against a persistent digest index that is bucketed and sorted by digest.

The index is a folder: bucketed, sorted Parquet files of (digest, keep_id, batch), known to the session catalog as an
external table, and found again by any later session.  Every batch of new data goes through the same steps: its distinct
digests are anti-joined with the index by sort-merge on the bucketing key, the fresh ones are appended under the batch's
name, and all results are read from the index.  A batch that is run again, after a lost job or by mistake, finds its own
name there and gets the results of its first run.

Contract of `deduplicate`: texts are equal when identical after lower-casing A-Z; null counts as empty; of equal
texts in one batch the largest id stays, a text that an earlier batch brought in keeps that batch's row.  Repeated
rows form one group; if they even share the id, every such row is reported with the same keeper and `kept` is true for
the rows that carry the keeper's id.  Empty tables give no rows; extra columns never enter.
"""

from __future__ import annotations

import hashlib

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from paircuration.llm.common import attach, scratch, settle


def _digest_batches(batches):
    for batch in batches:
        texts = pc.ascii_lower(pc.fill_null(batch.column(1), "")).cast(pa.large_binary())
        offsets = memoryview(texts.buffers()[1]).cast("q")[texts.offset : texts.offset + len(texts) + 1]
        data = memoryview(texts.buffers()[2]) if texts.buffers()[2] is not None else memoryview(b"")
        sums = [hashlib.sha256(data[offsets[i] : offsets[i + 1]]).digest() for i in range(len(texts))]
        yield pa.record_batch([batch.column(0), pa.array(sums, pa.binary())], names=["row_key", "digest"])


def digests(df: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(row_key, digest): narrow, one pass over the texts, which never move."""
    kind = df.schema[id_col].dataType.simpleString()
    return df.select(F.col(id_col).alias("row_key"), F.col(text_col).cast("string").alias("body")).mapInArrow(
        _digest_batches, f"row_key {kind}, digest binary"
    )


ROWS_A_BUCKET = 2_000_000


class DigestIndex:
    """Digest index below one folder; appends add sorted files to its buckets, `compact` merges them.

    `buckets` holds for a new index only (take about one per ROWS_A_BUCKET digests expected); an existing one keeps its own.
    """

    def __init__(self, spark: SparkSession, folder: str | None = None, buckets: int = 16, id_type: str = "bigint"):
        self.spark, self.folder = spark, (folder or scratch(spark, "digest-index")).rstrip("/")
        jvm = spark.sparkContext._jvm
        self._path = jvm.org.apache.hadoop.fs.Path
        self._fs = self._path(self.folder).getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
        held = self._versions()
        if held:
            self.buckets, self.id_type = held[-1][1], held[-1][2]
        else:
            self.buckets, self.id_type = buckets, id_type
            self._fs.mkdirs(self._path(self._place(0)))
        self._open(held[-1][0] if held else 0)

    def _versions(self) -> list[tuple[int, int, str]]:
        """(version, buckets, id type) of the folders of complete versions; their names carry all three."""
        if not self._fs.exists(self._path(self.folder)):
            return []
        names = [str(x.getPath().getName()) for x in self._fs.listStatus(self._path(self.folder))]
        return sorted((int(n.split("-")[1]), int(n.split("-")[2]), n.split("-", 3)[3]) for n in names if n.startswith("version-"))

    def _place(self, version: int) -> str:
        return f"{self.folder}/version-{version}-{self.buckets}-{self.id_type}"

    def _open(self, version: int) -> None:
        self.version, where = version, self._place(version)
        self.table = f"digest_index_{hashlib.sha256(where.encode()).hexdigest()[:16]}"
        self._declare(self.table, where)

    def _declare(self, table: str, where: str) -> None:
        self.spark.sql(f"""CREATE TABLE IF NOT EXISTS {table} (digest BINARY, keep_id {self.id_type}, batch STRING) USING parquet
            CLUSTERED BY (digest) SORTED BY (digest) INTO {self.buckets} BUCKETS LOCATION '{where}'""")

    def rows(self) -> DataFrame:
        self.spark.catalog.refreshTable(self.table)
        return self.spark.table(self.table)

    def append(self, fresh: DataFrame) -> None:
        """Rows (digest, keep_id, batch), one sorted file for each bucket."""
        rows = fresh.select("digest", F.col("keep_id").cast(self.id_type).alias("keep_id"), "batch").repartition(self.buckets, "digest").sortWithinPartitions("digest")
        rows.write.insertInto(self.table)

    def compact(self) -> None:
        """Rewrite every bucket as one sorted file, in a new version that takes over when it is complete."""
        old, draft = self._place(self.version), f"{self.folder}/draft-{self.version + 1}"
        self._fs.delete(self._path(draft), True)
        self._fs.mkdirs(self._path(draft))
        table = f"{self.table}_draft"
        self._declare(table, draft)
        self.rows().repartition(self.buckets, "digest").sortWithinPartitions("digest").write.insertInto(table)
        self.spark.sql(f"DROP TABLE {table}")
        self.forget()
        self._fs.rename(self._path(draft), self._path(self._place(self.version + 1)))
        self._open(self.version + 1)
        self._fs.delete(self._path(old), True)

    def forget(self) -> None:
        """Drop the catalog entry; the files stay."""
        self.spark.sql(f"DROP TABLE IF EXISTS {self.table}")


def admit(marked: DataFrame, index: DigestIndex, batch: str) -> None:
    """Append the digests of (row_key, digest) that the index lacks, each with its largest id, under the batch's name.

    Copies are reduced map-side; the index meets one row per distinct digest, in a sort-merge anti join.
    """
    groups = marked.groupBy("digest").agg(F.max("row_key").alias("keep_id"))
    index.append(groups.join(index.rows().select("digest").hint("merge"), "digest", "left_anti").withColumn("batch", F.lit(batch)))


def _reported(marked: DataFrame, index: DigestIndex, batch: str | None, id_col: str) -> DataFrame:
    """Results of rows whose digests have all been admitted; hot groups are attached by a bounded broadcast."""
    sizes = marked.groupBy("digest").agg(F.count(F.lit(1)).alias("group_size"))
    fresh = F.lit(True) if batch is None else F.col("batch") == batch
    groups = settle(sizes.join(index.rows().hint("merge"), "digest").select("digest", "keep_id", "group_size", fresh.alias("fresh")), "digest-groups")
    return attach(marked, groups, "digest", "group_size").select(
        F.col("row_key").alias(id_col), "keep_id", F.col("group_size").cast("long").alias("group_size"),
        (F.col("fresh") & F.col("row_key").eqNullSafe(F.col("keep_id"))).alias("kept"), F.lower(F.hex("digest")).alias("text_sha256"))


def deduplicate(df: DataFrame, index: DigestIndex, batch: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row of the batch: id, keep_id, group_size in the batch, kept, digest; fresh digests join the index."""
    marked = settle(digests(df, id_col, text_col), "digests")
    admit(marked, index, batch)
    return _reported(marked, index, batch, id_col)


def op2_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents, brought in by two batches: the upper half of the id range, then the rest, so larger ids come first."""
    marked = settle(digests(spark.read.parquet(f"{sf_dir}/documents.parquet"), "doc_id", "text"), "digests")
    n, low, high = marked.agg(F.count(F.lit(1)), F.min("row_key"), F.max("row_key")).first()
    index = DigestIndex(spark, buckets=max(16, -(-n // ROWS_A_BUCKET)))
    upper = F.coalesce(F.col("row_key") >= F.lit(((low or 0) + (high or 0)) // 2), F.lit(False))
    admit(marked.filter(upper), index, "upper")
    admit(marked.filter(~upper), index, "lower")
    out = _reported(marked, index, None, "doc_id")
    index.forget()
    return out


_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
OP2_SQL = f"""
WITH d AS (SELECT doc_id, sha256(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}')) AS text_sha256 FROM documents)
SELECT doc_id, max(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size,
       doc_id = max(doc_id) OVER w AS kept, text_sha256
FROM d WINDOW w AS (PARTITION BY text_sha256)
"""
