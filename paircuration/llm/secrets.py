"""Secret scans over an incremental blob ledger. DataFrame and SQL functions only.

Every version of a text is content-addressed by the SHA-256 of its bytes.  The ledger records, for each pair of blob
and rule version, the spans found; a scan reads only blobs whose pair is not in the ledger yet, and findings are joined
back to all paths (here: rows) that ever held the blob.

Spans are code points, end exclusive, one per regular-expression match, leftmost and non-overlapping for each kind.
Null text counts as empty and has no spans; repeated rows share a blob and each gets its findings; null ids are kept;
an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from paircuration.llm.common import attach, scratch, settle

# Kinds in their report order, pattern, and the least length of the group that decides (0: whole match).
BASE_RULES = (
    ("assign", r"""(?i)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 12),
    ("access", r"AKIA[A-Z0-9]{14,}", 0, 18),
    ("hex", r"[0-9a-f]{16,}", 0, 16),
)
EXTRA_RULES = (
    ("pem", r"-----BEGIN [A-Z ]*PRIVATE KEY-----", 0, 1),
    ("webtoken", r"eyJ[A-Za-z0-9_-]{8,}\.eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}", 0, 1),
    ("forge", r"gh[pousr]_[A-Za-z0-9]{36,}", 0, 1),
)
RULES = BASE_RULES + EXTRA_RULES


def version_of(rules: tuple) -> str:
    """Name of a rule set, derived from all its rules, so different rules never share ledger entries."""
    return hashlib.sha256(repr(rules).encode()).hexdigest()[:16]


def matches_of(body: Column, rule: tuple) -> Column:
    """array<struct<m,g,d>>: lengths of each match, of the gap before it, and of the group that decides."""
    _, pattern, group, _ = rule
    whole = F.regexp_extract_all(body, F.lit(pattern), F.lit(0))
    deciding = F.regexp_extract_all(body, F.lit(pattern), F.lit(group)) if group else whole
    sized = F.arrays_zip(F.transform(whole, F.length).alias("m"), F.transform(F.split(body, pattern, -1), F.length).alias("g"), F.transform(deciding, F.length).alias("d"))
    return F.when(body.rlike(pattern), F.slice(sized, F.lit(1), F.size(whole)))


def scan(blobs: DataFrame, rules: tuple = RULES) -> DataFrame:
    """(blob, spans) for each blob; spans ordered by start, then kind.

    Match i of a kind ends after i+1 gaps and matches: a running sum over the rows of one text and kind, so the cost is
    linear in the matches.
    """
    kinds = [F.struct(F.lit(i).alias("rank"), F.lit(rule[0]).alias("kind"), F.lit(rule[3]).alias("least"), matches_of(F.col("body"), rule).alias("sized")) for i, rule in enumerate(rules)]
    found = settle(blobs.select("blob", F.filter(F.array(*kinds), lambda k: k["sized"].isNotNull()).alias("kinds")), "matches")
    flat = found.select("blob", F.explode("kinds").alias("k")).select("blob", "k.rank", "k.kind", "k.least", F.posexplode("k.sized").alias("pos", "x"))
    upto = F.sum(F.col("x.g") + F.col("x.m")).over(Window.partitionBy("blob", "rank").orderBy("pos"))
    spans = flat.withColumn("end", upto.cast("bigint")).filter(F.col("x.d") >= F.col("least"))
    each = spans.groupBy("blob").agg(F.array_sort(F.collect_list(F.struct((F.col("end") - F.col("x.m")).alias("start"), "rank", "kind", "end"))).alias("spans"))
    none = F.expr("cast(array() as array<struct<start:bigint,rank:int,kind:string,end:bigint>>)")
    return found.select("blob").join(each, "blob", "left").select("blob", F.coalesce("spans", none).alias("spans"))


class BlobLedger:
    """Append-only parquet table (blob, version, spans) below one folder."""

    def __init__(self, spark: SparkSession, folder: str | None = None):
        self.spark, self.folder = spark, folder or scratch(spark, "blob-ledger")

    def _exists(self) -> bool:
        jvm = self.spark.sparkContext._jvm
        path = jvm.org.apache.hadoop.fs.Path(self.folder)
        return path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).exists(path)

    def rows(self, version: str) -> DataFrame | None:
        return self.spark.read.parquet(self.folder).filter(F.col("version") == version) if self._exists() else None

    def append(self, found: DataFrame, version: str) -> None:
        found.select("blob", F.lit(version).alias("version"), "spans").write.mode("append").parquet(self.folder)


def _body(text_col: str) -> Column:
    return F.coalesce(F.col(text_col).cast("string"), F.lit(""))


def record(df: DataFrame, ledger: BlobLedger, rules: tuple = RULES, text_col: str = "text") -> None:
    """Scan the blobs of `df` whose pair with this rule set is not in the ledger yet, each once, and append what is found.

    Copies are reduced to one text per blob map-side before anything moves.
    """
    version = version_of(rules)
    blobs = df.select(F.unhex(F.sha2(_body(text_col), 256)).alias("blob"), _body(text_col).alias("body")).groupBy("blob").agg(F.max("body").alias("body"))
    known = ledger.rows(version)
    if known is not None:
        blobs = blobs.join(known.select("blob").hint("merge"), "blob", "left_anti")
    ledger.append(scan(blobs, rules), version)


def findings(df: DataFrame, ledger: BlobLedger, rules: tuple = RULES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, blob, spans) of every row whose blob has been recorded, from the ledger.

    Only ids and digests move, and hot blobs are attached by a bounded broadcast.
    """
    paths = settle(df.select(F.col(id_col).alias("row_key"), F.unhex(F.sha2(_body(text_col), 256)).alias("blob")), "paths")
    sizes = paths.groupBy("blob").agg(F.count(F.lit(1)).alias("n"))
    found = settle(sizes.join(ledger.rows(version_of(rules)).select("blob", "spans").dropDuplicates(["blob"]), "blob"), "findings")
    return attach(paths, found, "blob", "n").select(F.col("row_key").alias(id_col), "blob", "spans")


def scan_versions(df: DataFrame, ledger: BlobLedger, rules: tuple = RULES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Record one version of a collection and return its findings."""
    record(df, ledger, rules, text_col)
    return findings(df, ledger, rules, id_col, text_col)


def _joined(spans: Column) -> Column:
    return F.concat_ws(",", F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))))


def op9_secret_scans(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents, recorded as two versions of the collection: the lower half of the id range, then what came later."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    low, high = docs.agg(F.min("doc_id"), F.max("doc_id")).first()
    earlier = F.coalesce(F.col("doc_id") < F.lit(((low or 0) + (high or 0)) // 2), F.lit(False))
    ledger = BlobLedger(spark)
    record(docs.filter(earlier), ledger)
    record(docs.filter(~earlier), ledger)
    found = findings(docs, ledger)
    count = lambda kind: F.size(F.filter("spans", lambda s: s["kind"] == kind)).cast("bigint")
    base = F.filter("spans", lambda s: s["rank"] < len(BASE_RULES))
    return found.select("doc_id", *[count(rule[0]).alias(f"n_{rule[0]}") for rule in BASE_RULES],
                        F.sha2(_joined(base), 256).alias("base_sha256"), _joined(F.col("spans")).alias("spans"))
