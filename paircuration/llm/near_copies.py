"""SimHash near-copies at a stated similarity: Jaccard of at least 0.8 over five-word shingles.

Ball hashing alone cannot do this: at similarity 0.8 two 64-bit fingerprints differ in about ten bits, and the variants
within half of that radius are some ten million a fingerprint.  So the stage has three sources of candidates and one exact
verification of them all on whole shingle sets; no document goes without a verified neighbour.

1. Balls: fingerprints within three bits, by meet-in-the-middle ball hashing (`simhash.links`).
2. Hubs: 24 MinHash bands of four.  A pair at similarity 0.8 misses all bands with probability 3e-6.  In each band
   every member is compared with one hub, drawn anew for each band.
3. The rest, exactly: links of the first two sources unite nodes.  Nodes of bands that still hold two components
   enter a prefix-filtered set join.  Shingles are ordered by rarity; two sets can reach the similarity only if they share a
   shingle of their prefixes, and only pairs from two components are formed.

Equal sets are one node from the start.  No band, bucket or group is capped.  A band's hub and a shingle's leading
component are map-side aggregates that are settled and joined back, both sides straight from exchanges, so the adaptive
skew join can split what one band or shingle holds.

Defined results: texts are lower-cased in A-Z only; null counts as empty; all texts without words are copies of each
other; a text of fewer than five words is one shingle; rows without an id stay if nothing they are copies of has one;
repeated rows are reduced to one; an empty table gives no rows; extra columns pass through.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from paircuration.llm import simhash
from paircuration.llm.common import pieces, settle

WORDS, TENTHS, SEED = 5, 8, 42  # whole tenths, so the comparison is exact
BANDS, ROWS = 24, 4
MAP = 8  # words of a parity map
LAST = 8  # earlier shingles that a prefix row carries
_draw = np.random.default_rng(SEED)
_ODD = _draw.integers(0, 1 << 63, BANDS * ROWS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_ADD = _draw.integers(0, 1 << 63, BANDS * ROWS, dtype=np.uint64)


def shingles(text: bytes) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the text's shingles."""
    words = text.lower().split()  # bytes: A-Z only, and ASCII white space only
    n = len(words)
    if n == 0:
        return np.empty(0, dtype=np.uint64)
    digest, body = xxhash.xxh64_intdigest, b" ".join(words)
    if n <= WORDS:
        return np.array([digest(body, SEED)], dtype=np.uint64)
    sizes = np.fromiter(map(len, words), np.int64, n)
    ends = np.cumsum(sizes + 1) - 1
    starts = (ends - sizes)[: n - WORDS + 1].tolist()
    return np.unique(np.fromiter((digest(body[a:b], SEED) for a, b in zip(starts, ends[WORDS - 1 :].tolist())), np.uint64, len(starts)))


def band_keys(found: np.ndarray) -> list[int]:
    """One signed 64-bit key per band; none for an empty set."""
    if not len(found):
        return []
    least = np.full(BANDS * ROWS, np.iinfo(np.uint64).max, dtype=np.uint64)
    for at in range(0, len(found), 1024):
        np.minimum(least, (found[at : at + 1024, None] * _ODD + _ADD).min(axis=0), out=least)
    return [simhash._signed(xxhash.xxh64_intdigest(part.tobytes(), i)) for i, part in enumerate(least.reshape(BANDS, ROWS))]


def parity_map(found: np.ndarray) -> np.ndarray:
    """64 * MAP bits; each is the parity of the number of shingles whose hash names it."""
    odd = np.bincount((found & np.uint64(64 * MAP - 1)).astype(np.int64), minlength=64 * MAP) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").view(np.int64)


def _texts(column):
    return pc.fill_null(column, "").cast(pa.large_binary())


def _node_batches(batches):
    for batch in batches:
        texts = _texts(batch.column(2))
        for at, to in pieces(texts):
            nodes, sizes, marks, keys = [], [], [], []
            for text in texts.slice(at, to - at):
                found = shingles(text.as_py())
                nodes.append(xxhash.xxh3_128_digest(found.tobytes()))
                sizes.append(len(found))
                marks.append(simhash._signed(simhash.majority(found)))
                keys.append(band_keys(found))
            part = batch.slice(at, to - at)
            yield pa.record_batch([part.column(0), part.column(1), pa.array(nodes, pa.binary()), pa.array(sizes, pa.int32()), pa.array(marks, pa.int64()),
                                   pa.array(keys, pa.list_(pa.int64()))], names=["row_key", "digest", "node", "size", "mark", "keys"])


def _set_batches(batches):
    for batch in batches:
        texts = _texts(batch.column(1))
        for at, to in pieces(texts):
            sets = [shingles(t.as_py()) for t in texts.slice(at, to - at)]
            yield pa.record_batch([batch.column(0).slice(at, to - at), pa.array([x.view(np.int64) for x in sets], pa.list_(pa.int64())),
                                   pa.array([parity_map(x) for x in sets], pa.list_(pa.int64()))], names=["node", "grams", "bits"])


def _pairs(met: DataFrame, left: str, right: str) -> DataFrame:
    """Distinct pairs (a, b), a < b, whose set sizes alone do not rule the similarity out."""
    sized = met.filter(f"{left}.node <> {right}.node AND 10 * least({left}.size, {right}.size) >= {TENTHS} * greatest({left}.size, {right}.size)")
    return sized.select(F.least(f"{left}.node", f"{right}.node").alias("a"), F.greatest(f"{left}.node", f"{right}.node").alias("b")).distinct()


def _verified(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """Pairs (a, b) whose whole shingle sets reach the similarity."""
    x, y = sets.select(F.col("node").alias("a"), F.col("grams").alias("x")), sets.select(F.col("node").alias("b"), F.col("grams").alias("y"))
    both = F.size(F.array_intersect("x", "y"))
    met = pairs.join(x, "a").join(y, "b").withColumn("both", both)
    return met.filter(f"10 * both >= {TENTHS} * (size(x) + size(y) - both)").select("a", "b")


def _ball_pairs(nodes: DataFrame) -> DataFrame:
    """Candidates within three bits: each node with the first node of its own fingerprint and of each hub it meets."""
    firsts = settle(nodes.groupBy("mark").agg(F.min(F.struct("node", "size")).alias("first")), "marks")
    active = settle(simhash.candidates(firsts.select("mark")), "active")
    hubs = firsts.select(F.col("mark").alias("hub"), "first")
    reached = simhash.links(active).join(hubs, "hub").select("mark", "first").union(firsts)
    return _pairs(nodes.select("mark", F.struct("node", "size").alias("me")).join(reached, "mark"), "me", "first")


def _bands(nodes: DataFrame) -> DataFrame:
    """(key, me, hub) of every member of a band that holds two nodes or more."""
    members = nodes.select(F.explode("keys").alias("key"), F.struct("node", "size").alias("me"))
    hubs = members.groupBy("key").agg(F.count(F.lit(1)).alias("n"), F.min_by("me", F.xxhash64("me.node", "key")).alias("hub")).filter("n > 1")
    return members.join(settle(hubs.select("key", "hub"), "hubs").hint("merge"), "key")


def _tree(edges: DataFrame) -> DataFrame:
    found = simhash.components(edges)
    return settle(found.union(found.select("root", "root").distinct()).toDF("node", "root"), "tree")


def _rest(met: DataFrame, tree: DataFrame, sets: DataFrame) -> DataFrame:
    """Candidate pairs (a, b) from different components, by a prefix-filtered join of the nodes in undecided bands.

    A node's unshared shingles are its rarest and use up places of its prefix.  Two sets that reach the similarity
    differ in at most a ninth of their sizes' sum, no fewer shingles differ than bits of the two parity maps, and what follows
    their first common shingle in the order has room for all they must share.  A pair is wanted at its first common shingle
    only: a row carries the last few shingles before its own, and a pair that shares one of them has been put out there or
    earlier.  All this is in the join's condition, so it puts out few rows a pair, however many shingles that pair shares.
    """
    rooted = met.select("key", F.col("me.node").alias("node")).join(tree, "node", "left").withColumn("root", F.coalesce("root", "node"))
    rooted = settle(rooted, "rooted")
    undecided = rooted.groupBy("key").agg(F.min("root").alias("low"), F.max("root").alias("high")).filter("low <> high").select("key")
    undecided = settle(undecided, "undecided-bands")
    nodes = rooted.join(undecided.hint("merge"), "key", "left_semi").select("node", "root").distinct()
    inside = settle(sets.join(nodes, "node").select("node", "root", "bits", F.size("grams").alias("size"), "grams"), "undecided")
    grams = inside.select("node", "size", F.explode("grams").alias("gram"))
    shared = settle(grams.groupBy("gram").agg(F.count(F.lit(1)).alias("n")).filter("n > 1"), "shared")
    known = grams.join(shared.hint("merge"), "gram").groupBy("node", "size").agg(F.array_sort(F.collect_list(F.struct("n", "gram"))).alias("known"))
    alone = F.col("size") - F.size("known")
    room = (F.col("size") - F.ceil(F.col("size") * TENTHS / F.lit(10)) + 1 - alone).cast("int")
    taken = known.withColumn("alone", alone).withColumn("room", room).filter("room > 0").select("node", "alone", F.slice("known.gram", F.lit(1), F.col("room")).alias("taken"))
    prefix = taken.select("node", "alone", "taken", F.posexplode("taken").alias("i", "gram"))
    before = F.slice("taken", F.greatest(F.col("i") - LAST + 1, F.lit(1)), F.least("i", F.lit(LAST)))
    prefix = prefix.select("node", "gram", (F.col("alone") + F.col("i") + 1).alias("place"), before.alias("before"))
    prefix = settle(prefix.join(inside.select("node", "root", "size", *[F.col("bits")[i].alias(f"b{i}") for i in range(MAP)]), "node"), "prefix")
    per = prefix.groupBy("gram", "root").agg(F.count(F.lit(1)).alias("n"))
    lead = per.groupBy("gram").agg(F.max(F.struct("n", "root")).alias("most"), F.count(F.lit(1)).alias("roots")).filter("roots > 1").select("gram", F.col("most.root").alias("lead"))
    lead = settle(lead, "leads")
    living = settle(prefix.join(lead.hint("merge"), "gram"), "living")
    differ = " + ".join(f"bit_count(x.b{i} ^ y.b{i})" for i in range(MAP))
    near = f"10 * least(x.size, y.size) >= {TENTHS} * greatest(x.size, y.size) AND {10 + TENTHS} * ({differ}) <= {10 - TENTHS} * (x.size + y.size)"
    rest = f"{10 + TENTHS} * (1 + least(x.size - x.place, y.size - y.place)) >= {TENTHS} * (x.size + y.size)"
    once = "(y.root = y.lead OR x.node < y.node) AND NOT arrays_overlap(x.before, y.before)"
    met = living.filter("root <> lead").alias("x").join(living.alias("y").hint("merge"), F.expr(f"x.gram = y.gram AND x.root <> y.root AND {rest} AND {near} AND {once}"))
    return met.select(F.least("x.node", "y.node").alias("a"), F.greatest("x.node", "y.node").alias("b")).distinct()


def keep_first(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One document of each component of verified near copies, the one with the smallest id, with all its columns."""
    kind = df.schema[id_col].dataType.simpleString()
    body = F.col(text_col).cast("string").alias("body")
    rows = df.select(F.col(id_col).alias("row_key"), simhash.text_digest(text_col).alias("digest"), body)
    marked = settle(rows.mapInArrow(_node_batches, f"row_key {kind}, digest binary, node binary, size int, mark bigint, keys array<bigint>"), "nodes")
    best = settle(simhash.first_rows(marked, "node"), "firsts")
    nodes = settle(marked.select("node", "size", "mark", "keys").distinct(), "distinct-nodes")

    met = settle(_bands(nodes), "bands")
    pairs = settle(_pairs(met, "me", "hub").union(_ball_pairs(nodes)).distinct(), "pairs")
    needed = met.select("me.node").union(pairs.select("a")).union(pairs.select("b")).distinct()
    readers = settle(best.join(needed, "node", "left_semi").select("node", F.col("best.row_key").alias("_id"), F.col("best.digest").alias("_stay")), "readers")
    on = F.col("row_key").eqNullSafe(F.col("_id")) & (F.col("digest") == F.col("_stay"))
    sets = rows.join(readers.hint("shuffle_hash"), on).select("node", "body").mapInArrow(_set_batches, "node binary, grams array<bigint>, bits array<bigint>")
    sets = settle(sets.dropDuplicates(["node"]), "sets")

    first = settle(_verified(pairs, sets), "links")
    second = settle(_verified(settle(_rest(met, _tree(first), sets), "pairs"), sets), "links")
    return simhash.keep_rows(df, best, _tree(first.union(second)), "node", id_col, text_col)
