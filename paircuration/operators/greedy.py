"""The ordered pass: a row is dropped iff an earlier row that was kept is similar to it.

The sequential pass over an index keeps the lexicographically first maximal independent set of the similarity graph.
Small components are passed over as they are, each in one task; large ones in rounds: an open row whose earlier
neighbours are all dropped is kept; later neighbours of kept rows are dropped.  The earliest open row always settles, so
rounds are bounded by the longest ascending chain.  State is settled in the shared folder between rounds; rows without
edges never enter.

Defined results: repeated edges count once; ids are unique and not null; without edges there are no verdicts, and every row
stays.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from paircuration.sources.scratch import discard, settle


def _in_order(edges: pa.Table) -> pa.Table:
    """The sequential pass itself, over whole components."""
    dropped, edges = set(), edges.sort_by("hi")
    for lo, hi in zip(edges["lo"].to_pylist(), edges["hi"].to_pylist()):
        if lo not in dropped:  # all edges that could drop it have come before
            dropped.add(hi)
    ids = pa.chunked_array([*edges["lo"].chunks, *edges["hi"].chunks], edges["lo"].type).unique()
    return pa.table({"id": ids, "kept": pa.array([x not in dropped for x in ids.to_pylist()], pa.bool_())})


def resolve(edges: DataFrame, most: int = 250_000) -> DataFrame:
    """(id, kept) of every row that has an edge; edges are (lo, hi) with lo earlier in the order.

    Components do not meet, so those of up to `most` edges are passed over in order, bundled into groups of about as many
    edges; an edge moves once for that.  Only larger components take distributed rounds.
    """
    kind = edges.schema["lo"].dataType.simpleString()
    edges = settle(edges.select("lo", "hi").distinct())
    tree = settle(components_keep_first(edges).select(F.col("id").alias("lo"), "root"))
    rooted = settle(edges.join(tree, "lo"))
    per = settle(rooted.groupBy("root").agg(F.count(F.lit(1)).alias("n")))
    total, largest = per.agg(F.coalesce(F.sum("n"), F.lit(0)), F.coalesce(F.max("n"), F.lit(0))).first()
    large = per.filter(F.col("n") > most).select("root").hint("merge")
    small = rooted if largest <= most else rooted.join(large, "root", "left_anti")
    groups = max(1, -(-total // most))
    done = small.select("lo", "hi", F.pmod(F.xxhash64("root"), F.lit(groups)).alias("bundle")).groupBy("bundle").applyInArrow(_in_order, f"id {kind}, kept boolean")
    return done if largest <= most else done.union(_rounds(rooted.join(large, "root", "left_semi")))


def _rounds(edges: DataFrame) -> DataFrame:
    """The same by rounds over all edges at once."""
    edges = settle(edges.select("lo", "hi").distinct())
    nodes = edges.select(F.col("lo").alias("id")).union(edges.select("hi")).distinct()
    open_edges, open_nodes = edges, settle(nodes)
    done = None
    while open_nodes.limit(1).count():
        blocked = open_edges.select(F.col("hi").alias("id")).distinct()
        kept = settle(open_nodes.join(blocked, "id", "left_anti"))
        dropped = settle(open_edges.join(kept.withColumnRenamed("id", "lo"), "lo", "left_semi").select(F.col("hi").alias("id")).distinct())
        settled = kept.withColumn("kept", F.lit(True)).union(dropped.withColumn("kept", F.lit(False)))
        done = settled if done is None else done.union(settled)
        open_nodes = settle(open_nodes.join(settled.select("id"), "id", "left_anti"))
        gone = settled.select("id")
        open_edges = settle(open_edges.join(gone.withColumnRenamed("id", "lo"), "lo", "left_anti").join(gone.withColumnRenamed("id", "hi"), "hi", "left_anti"))
    return done if done is not None else nodes.withColumn("kept", F.lit(True))


def resolve_buckets(idx: DataFrame, id_col: str) -> DataFrame:
    """Pair-free pass when sharing a bucket alone decides: (id, kept) of every row that shares a bucket.

    Buckets of one row never enter.  Each round keeps rows that are the smallest open member of all their buckets and
    drops everyone who shares a bucket with them: linear in index rows, and a bucket is only ever aggregated map-side and
    joined back, so hot buckets are harmless.  One status table and the remaining index are settled a round.
    """
    bucket = ["band", "key"]
    rows = idx.select(*bucket, F.col(id_col).alias("id"))
    shared = rows.groupBy(*bucket).agg(F.count(F.lit(1)).alias("n")).filter("n > 1").select(*bucket)
    state, done = settle(rows.join(shared, bucket, "left_semi")), None
    while state.limit(1).count():
        least = state.groupBy(*bucket).agg(F.min("id").alias("first"))
        kept = state.join(least, bucket).groupBy("id").agg(F.min((F.col("first") == F.col("id")).cast("int")).alias("kept"))
        known = state.join(kept, "id")
        taken = known.groupBy(*bucket).agg(F.max("kept").alias("taken"))
        status = known.join(taken, bucket).groupBy("id").agg(F.max("kept").alias("kept"), F.max("taken").alias("taken")).filter("taken = 1")
        status = settle(status.select("id", (F.col("kept") == 1).alias("kept")))
        done = status if done is None else done.union(status)
        state = settle(state.join(status.select("id"), "id", "left_anti"))
    return done if done is not None else state.select("id", F.lit(True).alias("kept"))


def components_keep_first(edges: DataFrame) -> DataFrame:
    """(id, kept, root): the ablation that keeps only the first row of each connected component.

    Alternating large-star and small-star rounds over the edges.  Least neighbours are map-side minima that are settled
    and joined back, so the adaptive skew join can split the edges of a star centre.  A round's tables go with the round.
    """
    def hooked(df):
        least = settle(df.groupBy("u").agg(F.min("v").alias("least")))
        used.append(least)
        return df.join(least.hint("merge"), "u").withColumn("m", F.least("least", "u"))

    now = settle(edges.select(F.greatest("lo", "hi").alias("u"), F.least("lo", "hi").alias("v")).distinct())
    before = None
    while True:
        state = now.agg(F.count(F.lit(1)), F.coalesce(F.bit_xor(F.xxhash64("u", "v")), F.lit(0)), F.coalesce(F.bit_xor(F.xxhash64("v", "u")), F.lit(0))).first()
        if state == before or state[0] == 0:
            break
        before, used = state, [now]
        both = now.union(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = settle(hooked(both).filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct())
        small = hooked(large)
        now = settle(small.select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v").union(small.select("u", F.col("m").alias("v"))).distinct())
        discard(*used, large)
    leaves = now.select(F.col("u").alias("id"), F.lit(False).alias("kept"), F.col("v").alias("root"))
    return leaves.union(now.select(F.col("v").alias("id"), F.lit(True), F.col("v")).distinct())
