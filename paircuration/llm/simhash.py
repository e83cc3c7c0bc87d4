"""SimHash near-duplicates, joined by meet-in-the-middle ball hashing.

A fingerprint is 64 bits over three-word shingles; two link at three or fewer differing bits.  Fingerprints of
distance d <= 2 share a variant within one flipped bit of each.  At d = 3 the popcounts differ in parity, and two of
the three bits lie in one 32-bit half: the even fingerprint flips one bit, the odd one flips two bits of one half, and
they meet.  So a shared variant proves a link to anyone within one bit of it, and each variant needs only links to its
smallest such member: no group is expanded into pairs.

Only fingerprints that can have a neighbour are expanded: d <= 3 leaves some half with at most one differing bit, and
a first shuffle on halves (the even half emits its 33 variants, the odd one itself) finds who meets anybody there.

Defined results: texts are lower-cased in A-Z only; null counts as empty; a text without words has fingerprint zero
and links like any other; repeated rows share a component; null ids never represent a component unless all ids are
null; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from paircuration.llm.common import attach, settle

WORDS, SEED = 3, 42
_weights = np.left_shift(np.uint64(1), np.arange(64, dtype=np.uint64))


def majority(hashes: np.ndarray) -> int:
    """Unsigned 64-bit value whose bits are those set in more than half of the hashes."""
    count = np.zeros(64, dtype=np.int64)
    for at in range(0, len(hashes), 16384):
        count += np.unpackbits(hashes[at : at + 16384].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(_weights[2 * count > len(hashes)].sum())


def fingerprint(text: bytes) -> int:
    """Unsigned 64-bit SimHash: a bit is set if more than half of all shingle hashes have it, repeats included."""
    words = text.lower().split()  # bytes: A-Z only, and ASCII white space only
    n = len(words)
    if n == 0:
        return 0
    digest = xxhash.xxh64_intdigest
    if n <= WORDS:
        return digest(b" ".join(words), SEED)
    body = b" ".join(words)
    sizes = np.fromiter(map(len, words), np.int64, n)
    ends = np.cumsum(sizes + 1) - 1
    starts = (ends - sizes)[: n - WORDS + 1].tolist()
    count, at = np.zeros(64, dtype=np.int64), 0
    ends = ends[WORDS - 1 :].tolist()
    while at < len(starts):
        part = np.array([digest(body[a:b], SEED) for a, b in zip(starts[at : at + 16384], ends[at : at + 16384])], dtype=np.uint64)
        count += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
        at += 16384
    return int(_weights[2 * count > len(starts)].sum())


def _fingerprint_batches(batches):
    for batch in batches:
        texts = pc.fill_null(batch.column(1), "").cast(pa.large_binary())
        marks = np.array([fingerprint(t.as_py()) for t in texts], dtype=np.uint64).view(np.int64)
        yield pa.record_batch([batch.column(0), pa.array(marks, pa.int64())], names=["row_key", "mark"])


def _digest_fingerprint_batches(batches):
    for batch in batches:
        for part in _fingerprint_batches([batch.select([0, 2])]):
            yield pa.record_batch([batch.column(0), batch.column(1), part.column(1)], names=["row_key", "digest", "mark"])


def text_digest(text_col: str):
    """16 bytes that tell apart rows that share an id; null counts as empty."""
    return F.unhex(F.md5(F.coalesce(F.col(text_col).cast("string"), F.lit("")).cast("binary")))


def fingerprints(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(row_key, mark): the fingerprint as a signed long. Narrow."""
    kind = df.schema[id_col].dataType.simpleString()
    return df.select(F.col(id_col).alias("row_key"), F.col(text_col).cast("string").alias("body")).mapInArrow(
        _fingerprint_batches, f"row_key {kind}, mark bigint")


def _signed(x: int) -> int:
    return x - (1 << 64) if x >= 1 << 63 else x


def _longs(values) -> F.col:
    return F.array(*[F.lit(_signed(v)).cast("bigint") for v in values])


def candidates(marks: DataFrame) -> DataFrame:
    """Fingerprints that meet another one within one bit on a 32-bit half: all that can have a link, and few others."""
    low = F.col("mark").bitwiseAND(F.lit(0xFFFFFFFF))
    high = F.shiftrightunsigned("mark", 32)
    halves = marks.select("mark", F.explode(F.array(low, high.bitwiseOR(F.lit(1 << 32)))).alias("half"))
    flips = _longs([0] + [1 << i for i in range(32)])
    even = F.bit_count(F.col("half").bitwiseAND(F.lit(0xFFFFFFFF))) % 2 == 0
    sent = halves.select("mark", "half", F.explode(F.when(
        even, F.transform(flips, lambda m: F.col("half").bitwiseXOR(m))).otherwise(F.array("half"))).alias("key"))
    sent = sent.select("mark", "key", (F.col("key") == F.col("half")).cast("int").alias("own"))
    met = sent.groupBy("key").agg(F.count(F.lit(1)).alias("n"), F.max("own").alias("owned")).filter("n >= 2 AND owned = 1").select("key")
    met = settle(met, "met-halves")  # joined back from files, so the skew join can split a half that very many share
    return sent.join(met.hint("merge"), "key", "left_semi").select("mark").distinct()


def links(marks: DataFrame) -> DataFrame:
    """(mark, hub): enough links of distance <= 3 to connect every two fingerprints that link."""
    one = [0] + [1 << i for i in range(64)]
    two = [(1 << j) | (1 << k) for h in (0, 32) for j in range(h, h + 32) for k in range(j + 1, h + 32)]
    single = marks.select("mark", F.explode(F.transform(_longs(one), lambda m: F.col("mark").bitwiseXOR(m))).alias("key"), F.lit(True).alias("near"))
    odd = marks.filter(F.bit_count("mark") % 2 == 1)
    double = odd.select("mark", F.explode(F.transform(_longs(two), lambda m: F.col("mark").bitwiseXOR(m))).alias("key"), F.lit(False).alias("near"))
    sent = single.union(double)
    hubs = sent.groupBy("key").agg(F.count(F.lit(1)).alias("n"), F.min(F.when(F.col("near"), F.col("mark"))).alias("hub"))
    hubs = settle(hubs.filter("n >= 2 AND hub IS NOT NULL").select("key", "hub"), "hubs")
    met = sent.join(hubs.hint("merge"), "key").filter("hub <> mark")
    close = F.bit_count(F.col("mark").bitwiseXOR(F.col("hub"))) <= 3  # the verification
    return met.filter(close).select("mark", "hub").distinct()


def components(edges: DataFrame, max_rounds: int = 64) -> DataFrame:
    """(node, root): the smallest node reachable, by alternating large-star and small-star rounds.

    `edges` has columns a and b of one type.  Each node's least neighbour is a map-side minimum that is settled and joined
    back, both sides straight from files, so the adaptive skew join can split the many edges of one star centre.  Every
    round is settled in the shared folder; the number of rounds grows with the logarithm of the graph's size.
    """
    def hooked(df):
        least = settle(df.groupBy("u").agg(F.min("v").alias("least")), "minima")
        return df.join(least.hint("merge"), "u").withColumn("m", F.least("least", "u"))

    now = edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).filter("u <> v").distinct()
    now, before = settle(now, "edges"), None
    for _ in range(max_rounds):
        state = now.agg(F.count(F.lit(1)), F.coalesce(F.bit_xor(F.xxhash64("u", "v")), F.lit(0)), F.coalesce(F.bit_xor(F.xxhash64("v", "u")), F.lit(0))).first()
        if state == before or state[0] == 0:
            break
        before = state
        both = now.union(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = settle(hooked(both).filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct(), "stars")
        small = hooked(large)
        nexts = small.select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v").union(small.select("u", F.col("m").alias("v"))).distinct()
        now = settle(nexts, "edges")
    else:
        raise RuntimeError("components did not converge")
    return now.select(F.col("u").alias("node"), F.col("v").alias("root"))


def _tree(groups: DataFrame) -> DataFrame:
    """(mark, root) of every fingerprint that has a link; `groups` has one row per fingerprint."""
    active = settle(candidates(groups.select("mark")), "active")
    found = components(links(active).select(F.col("mark").alias("a"), F.col("hub").alias("b")))
    return settle(found.select(F.col("node").alias("mark"), "root").union(
        found.select("root").distinct().select(F.col("root").alias("mark"), "root")), "tree")


def near_duplicates(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, fingerprint, component_id) per row: the smallest id reachable over links of at most three bits."""
    marked = settle(fingerprints(df, id_col, text_col), "fingerprints")
    groups = settle(marked.groupBy("mark").agg(F.min("row_key").alias("first"), F.count(F.lit(1)).alias("n")), "marks")
    tree = _tree(groups)
    smallest = tree.join(groups.select("mark", "first"), "mark").groupBy("root").agg(F.min("first").alias("smallest"))
    named = tree.join(smallest, "root").select("mark", "smallest")
    classes = settle(groups.join(named, "mark", "left").select(
        "mark", "n", F.coalesce("smallest", "first").alias("component_id")), "classes")
    out = attach(marked, classes, "mark", "n")
    return out.select(F.col("row_key").alias(id_col), F.lpad(F.lower(F.hex("mark")), 16, "0").alias("fingerprint"), "component_id")


def first_rows(marked: DataFrame, key: str) -> DataFrame:
    """(key, best) from (row_key, digest, key): the key's row of the smallest id, then digest, and how often it occurs."""
    per = marked.groupBy(key, "row_key", "digest").agg(F.count(F.lit(1)).alias("n"))
    return per.groupBy(key).agg(F.min(F.struct(F.col("row_key").isNull().alias("anonymous"), "row_key", "digest", "n")).alias("best"))


def keep_rows(df: DataFrame, best: DataFrame, tree: DataFrame, key: str, id_col: str, text_col: str) -> DataFrame:
    """Rows of `df` that are the first of their component, with all their columns.

    `best` is what first_rows returns, `tree` has (key, root) of the keys that have links.  A survivor is known by id and
    digest together, and only rows equal in both, which share a component, are reduced to one.  The survivors are the
    hashed side of the join, so no text is sorted.
    """
    rooted = best.join(tree, key, "left").groupBy(F.coalesce("root", key).alias("root")).agg(F.min("best").alias("best"))
    stay = settle(rooted.select(F.col("best.row_key").alias("_id"), F.col("best.digest").alias("_stay"), F.col("best.n").alias("_n")), "survivors")
    digest = F.unhex(F.md5(F.coalesce(df[text_col].cast("string"), F.lit("")).cast("binary")))

    def staying(kept: DataFrame) -> DataFrame:
        kept = kept.hint("shuffle_hash")
        return df.join(kept, df[id_col].eqNullSafe(kept["_id"]) & (digest == kept["_stay"]), "left_semi")

    if not stay.filter("_n > 1").limit(1).count():
        return staying(stay)
    mark = "digest of " + " ".join(df.columns)  # a name that no column has
    many = staying(stay.filter("_n > 1")).withColumn(mark, text_digest(text_col)).dropDuplicates([id_col, mark])
    return staying(stay.filter("_n = 1")).union(many.select(*df.columns))


def keep_first(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One document of each component, the one with the smallest id, with all its columns.

    Rows of different components stay apart even if they share an id or have none; a row with a null id is kept if
    nothing it links to has an id, one for each such component.
    """
    kind = df.schema[id_col].dataType.simpleString()
    marked = settle(df.select(F.col(id_col).alias("row_key"), text_digest(text_col).alias("digest"), F.col(text_col).cast("string").alias("body")).mapInArrow(
        _digest_fingerprint_batches, f"row_key {kind}, digest binary, mark bigint"), "fingerprints")
    best = settle(first_rows(marked, "mark"), "marks")
    return keep_rows(df, best, _tree(best), "mark", id_col, text_col)


def op10_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet"))
