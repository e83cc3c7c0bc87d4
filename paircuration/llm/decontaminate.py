"""Benchmark decontamination: a prefix-filtered set join with positional bounds and exact verification.

Every benchmark item is cut into windows of 13 consecutive words (a shorter item is one window).  A window is a set of
five-word shingles, ordered by rarity in the corpus; because containment must be complete, its necessary prefix is one
shingle, the rarest.  Documents join on prefix shingles only; the shingle's offset fixes where the window would have to
start, which must lie inside the document; the words there are then compared one by one.

Windows and shingles are made in the executors, and one pass over the corpus counts all shingles behind a bit map of
fixed size.  The windows are dealt into blocks of bounded number and bytes, by their hash.  The usual benchmark is one
block, and judging is one narrow pass.  Of several, only one is alive at a time: each takes a pass that puts out the hits
of the documents that have any, and the hits are merged at the end.

Defined results: null and word-less texts have no words, no hits and are clean; an item without words never occurs;
repeated items and rows are handled row by row; item ids are compared as strings; empty tables give empty results or
clean documents; extra columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from paircuration.llm.common import settle

WINDOW, SHINGLE = 13, 5
BLOCK_WINDOWS, BLOCK_BYTES = 500_000, 64 << 20  # windows, and bytes of their words, that a broadcast block holds at most, about
_BITS = 22  # of the bit map of shingles
_WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
_BASE, _STEP = 0x9E3779B97F4A7C15 | 1, 0xC2B2AE3D27D4EB4F | 1
_MASK = (1 << 64) - 1
_CHUNK = 1 << 20

_lower = np.arange(256, dtype=np.uint8)
_lower[65:91] += 32
_inside = np.zeros(256, dtype=bool)
_inside[48:58] = _inside[97:123] = _inside[128:] = True
_powers = {"n": 0}


def _power_tables(n: int):
    """Powers of the base and of its inverse modulo 2^64, grown on demand."""
    if _powers["n"] < n:
        size = max(n, 2 * _CHUNK)
        inverse = pow(_BASE, -1, 1 << 64)
        for name, base in (("up", _BASE), ("down", inverse)):
            table = np.full(size, np.uint64(base), dtype=np.uint64)
            table[0] = 1
            _powers[name] = np.cumprod(table, dtype=np.uint64)
        _powers["n"] = size
    return _powers["up"], _powers["down"]


def _mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    return h ^ (h >> np.uint64(32))


class Words:
    """Words of some concatenated texts: byte spans, 64-bit hashes and owning text, without a Python object per word."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray):
        self.data = _lower[data]
        inside = _inside[self.data]
        n = len(data)
        begin = inside.copy()
        begin[1:] &= ~inside[:-1]
        firsts = offsets[:-1][offsets[:-1] < n]
        begin[firsts] = inside[firsts]
        finish = inside.copy()
        finish[:-1] &= ~inside[1:] | begin[1:]
        self.start, self.end = np.flatnonzero(begin), np.flatnonzero(finish) + 1
        up, down = _power_tables(n + 1)
        total = np.zeros(n + 1, dtype=np.uint64)
        np.cumsum(self.data.astype(np.uint64) * up[:n], out=total[1:])
        self.hash = _mix((total[self.end] - total[self.start]) * down[self.start])
        self.owner = np.searchsorted(offsets, self.start, side="right") - 1
        bounds = np.searchsorted(self.start, offsets)
        self.first, self.count = bounds[:-1], np.diff(bounds)

    def text(self, i: int, n: int) -> bytes:
        return b" ".join(self.data[a:b].tobytes() for a, b in zip(self.start[i : i + n].tolist(), self.end[i : i + n].tolist()))

    def shingles(self, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Hash of the k words from each position on, and whether all of them are in one text."""
        n = max(0, len(self.hash) - k + 1)
        out = np.zeros(n, dtype=np.uint64)
        for j in range(k):
            out = out * np.uint64(_STEP) + self.hash[j : j + n]
        return _mix(out + np.uint64(k)), self.owner[:n] == self.owner[k - 1 : k - 1 + n]


def _window_batches(batches):
    """(item, body, hashes, shingles) of every distinct window of each item."""
    for batch in batches:
        for at, _, words in _pieces(batch, 1, 0):
            n = len(words.hash)
            seen, rows = set(), []
            for i in range(max(1, n - WINDOW + 1) if n else 0):
                size = min(n, WINDOW)
                body = words.text(i, size)
                if body not in seen:
                    seen.add(body)
                    h = words.hash[i : i + size]
                    rows.append((body, h.tobytes(), _shingles_of(h).view(np.int64)))
            if rows:
                yield pa.record_batch([pa.array([batch.column(0)[at].as_py() or ""] * len(rows)), pa.array([r[0] for r in rows], pa.binary()),
                                       pa.array([r[1] for r in rows], pa.binary()), pa.array([r[2] for r in rows], pa.list_(pa.int64()))], names=["item", "body", "hashes", "shingles"])


def _shingles_of(h: np.ndarray) -> np.ndarray:
    """Hashes of a window's shingles, in order; a shorter window is one shingle."""
    k = min(SHINGLE, len(h))
    acc = np.zeros(len(h) - k + 1, dtype=np.uint64)
    for j in range(k):
        acc = acc * np.uint64(_STEP) + h[j : j + len(acc)]
    return _mix(acc + np.uint64(k))


class Block:
    """A bounded set of benchmark windows with their prefix shingles."""

    def __init__(self, rows: list):
        """`rows` have item, body, hashes, and the prefix: its shingle and its offset in the window."""
        names = sorted({r["item"] for r in rows})
        number = {name: i for i, name in enumerate(names)}
        self.items = names
        self.windows = [(number[r["item"]], bytes(r["body"])) for r in rows]
        hashes = [np.frombuffer(r["hashes"], np.uint64) for r in rows]
        self.length = np.array([len(h) for h in hashes], dtype=np.int64)
        self.width = np.minimum(self.length, SHINGLE)
        self.offset = np.array([r["offset"] for r in rows], dtype=np.int64)
        self.prefix = np.array([r["prefix"] for r in rows], dtype=np.int64).view(np.uint64)
        self.matrix = np.zeros((len(rows), WINDOW), dtype=np.uint64)
        for i, h in enumerate(hashes):
            self.matrix[i, : len(h)] = h
        order = np.lexsort((self.prefix, self.width))
        self.lookup = {}
        for k in np.unique(self.width):
            own = order[self.width[order] == k]
            self.lookup[int(k)] = (self.prefix[own], own)

    def occurrences(self, words: Words) -> tuple[np.ndarray, np.ndarray]:
        """(word position, window) of every occurrence."""
        found = []
        for k, (prefix, own) in self.lookup.items():
            hashes, whole = words.shingles(k)
            spots = np.flatnonzero(_maybe(hashes, prefix) & whole)
            left = np.searchsorted(prefix, hashes[spots], side="left")
            right = np.searchsorted(prefix, hashes[spots], side="right")
            many = right - left
            spots, left, many = spots[many > 0], left[many > 0], many[many > 0]
            if not len(spots):
                continue
            window = own[np.repeat(left - np.cumsum(many) + many, many) + np.arange(many.sum())]
            at = np.repeat(spots, many)
            start, owner = at - self.offset[window], words.owner[at]
            last = words.first[owner] + words.count[owner]
            fits = (start >= words.first[owner]) & (start + self.length[window] <= last)
            start, window = start[fits], window[fits]
            for j in range(WINDOW):
                live = self.length[window] > j
                same = ~live
                same[live] = words.hash[start[live] + j] == self.matrix[window[live], j]
                start, window = start[same], window[same]
            known = self.windows
            exact = [words.text(s, n) == known[w][1] for s, w, n in zip(start.tolist(), window.tolist(), self.length[window].tolist())]
            exact = np.array(exact, dtype=bool)
            found.append((start[exact], window[exact]))
        if not found:
            return np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64)
        return np.concatenate([f[0] for f in found]), np.concatenate([f[1] for f in found])


def _maybe(hashes: np.ndarray, table: np.ndarray) -> np.ndarray:
    """A membership pre-test without false negatives."""
    bits = np.zeros(1 << _BITS, dtype=bool)
    bits[(table >> np.uint64(64 - _BITS)).astype(np.int64)] = True
    return bits[(hashes >> np.uint64(64 - _BITS)).astype(np.int64)]


def _pieces(batch: pa.RecordBatch, column: int, chunk: int = _CHUNK) -> Iterator[tuple[int, int, Words]]:
    """Rows of a batch in pieces of about a megabyte, one long text alone if need be; with no chunk, row by row."""
    texts = pc.fill_null(batch.column(column), "").cast(pa.large_string())
    offsets = np.frombuffer(texts.buffers()[1], dtype=np.int64)[texts.offset : texts.offset + len(texts) + 1]
    data = np.frombuffer(texts.buffers()[2], dtype=np.uint8) if texts.buffers()[2] is not None and texts.buffers()[2].size else np.zeros(0, np.uint8)
    at = 0
    while at < len(texts):
        to = max(at + 1, int(np.searchsorted(offsets, offsets[at] + chunk, side="right")) - 1) if chunk else at + 1
        to = min(to, len(texts))
        yield at, to, Words(data[offsets[at] : offsets[to]], offsets[at : to + 1] - offsets[at])
        at = to


def _frequencies(docs: DataFrame, text_col: str, shingles: DataFrame) -> DataFrame:
    """(shingle, n) of the (shingle, width) that occur in the corpus: one pass, whatever the number of windows.

    A bit map of fixed size keeps most of the corpus from travelling; the join drops what it lets through by chance.
    """
    cells = shingles.select("width", F.shiftrightunsigned("shingle", 64 - _BITS).cast("int").alias("cell")).distinct().collect()  # at most SHINGLE * 2^_BITS
    maps: dict[int, np.ndarray] = {}
    for k, cell in cells:
        maps.setdefault(k, np.zeros(1 << _BITS, dtype=bool))[cell] = True
    sent = docs.sparkSession.sparkContext.broadcast({k: np.packbits(m) for k, m in maps.items()})

    def count(batches):
        bits = {k: np.unpackbits(m).astype(bool) for k, m in sent.value.items()}
        for batch in batches:
            for _, _, words in _pieces(batch, 0):
                for k, own in bits.items():
                    hashes, whole = words.shingles(k)
                    found, n = np.unique(hashes[own[(hashes >> np.uint64(64 - _BITS)).astype(np.int64)] & whole], return_counts=True)
                    if len(found):
                        yield pa.record_batch([pa.array(found.view(np.int64)), pa.array(n.astype(np.int64))], names=["shingle", "n"])

    seen = docs.select(F.col(text_col).cast("string").alias("body")).mapInArrow(count, "shingle bigint, n bigint")
    return seen.groupBy("shingle").agg(F.sum("n").alias("n")).join(shingles.select("shingle").distinct().hint("merge"), "shingle")


def _prepared(docs: DataFrame, benchmark: DataFrame, text_col: str, item_col: str, item_text_col: str) -> tuple[DataFrame, int]:
    """Windows with their prefixes (the rarest shingle; ties by hash, so every run chooses alike) and blocks, and how many blocks."""
    source = benchmark.select(F.col(item_col).cast("string").alias("item"), F.col(item_text_col).cast("string").alias("body"))
    windows = source.mapInArrow(_window_batches, "item string, body binary, hashes binary, shingles array<bigint>").dropDuplicates(["item", "body"])
    windows = settle(windows, "windows")
    total, size = windows.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.length("body")), F.lit(0))).first()
    width = F.least(F.lit(SHINGLE), (F.length("hashes") / 8).cast("int"))
    each = windows.select("item", "body", width.alias("width"), F.posexplode("shingles").alias("offset", "shingle"))
    counted = settle(_frequencies(docs, text_col, each.select("shingle", "width").distinct()), "frequencies")
    best = each.join(counted.hint("merge"), "shingle", "left").groupBy("item", "body").agg(
        F.min(F.struct(F.coalesce("n", F.lit(0)).alias("n"), "shingle", "offset")).alias("best"))
    blocks = max(1, -(-total // BLOCK_WINDOWS), -(-size // BLOCK_BYTES))
    ready = windows.join(best.hint("merge"), ["item", "body"]).select("item", "body", "hashes", F.col("best.shingle").alias("prefix"), F.col("best.offset").alias("offset"),
                                                        F.pmod(F.xxhash64("item", "body"), F.lit(blocks)).cast("int").alias("block"))
    return settle(ready, "prefixes"), blocks


def _sent(ready: DataFrame, block: int):
    rows = ready.filter(F.col("block") == block).collect()  # bounded by the number of blocks
    return ready.sparkSession.sparkContext.broadcast(Block(rows)) if rows else None


def _spans(words: Words, block: Block, rows: int) -> tuple[list[list[tuple[int, int]]], list[set]]:
    """Hit runs of word positions (merged, end exclusive) and items of each of the texts."""
    items: list[set] = [set() for _ in range(rows)]
    edge = np.zeros(len(words.hash) + 1, dtype=np.int64)
    start, window = block.occurrences(words)
    np.add.at(edge, start, 1)
    np.add.at(edge, start + block.length[window], -1)
    for owner, w in zip(words.owner[start].tolist(), window.tolist()):
        items[owner].add(block.items[block.windows[w][0]])
    inside = np.concatenate([[False], np.cumsum(edge[:-1]) > 0, [False]])
    first = np.zeros(len(words.hash) + 1, dtype=bool)
    first[words.first] = True  # a run ends with its text
    begin = np.flatnonzero(inside[1:-1] & (~inside[:-2] | first[:-1]))
    end = np.flatnonzero(inside[1:-1] & (~inside[2:] | first[1:])) + 1
    spans: list[list[tuple[int, int]]] = [[] for _ in range(rows)]
    owners = words.owner[begin]
    for owner, x, y in zip(owners.tolist(), (begin - words.first[owners]).tolist(), (end - words.first[owners]).tolist()):
        spans[owner].append((x, y))
    return spans, items


def _judged(docs: DataFrame, sent, every: bool, id_col: str, text_col: str) -> DataFrame:
    """(row_key, digest, n_words, spans, items) of every document, or only of those with hits. Narrow."""
    kind = docs.schema[id_col].dataType.simpleString()
    span = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))

    def judge(batches):
        for batch in batches:
            for at, to, words in _pieces(batch, 2):
                spans, items = _spans(words, sent.value, to - at) if sent is not None else ([[]] * (to - at), [()] * (to - at))
                out = pa.record_batch(
                    [batch.column(0).slice(at, to - at), batch.column(1).slice(at, to - at), pa.array(words.count.astype(np.int64)),
                     pa.array([[{"start": a, "end": b} for a, b in x] for x in spans], span), pa.array([sorted(x) for x in items], pa.list_(pa.string()))],
                    names=["row_key", "digest", "n_words", "spans", "items"])
                yield out if every else out.filter(pa.array([bool(x) for x in items], pa.bool_()))

    body = F.col(text_col).cast("string")
    rows = docs.select(F.col(id_col).alias("row_key"), F.unhex(F.md5(F.coalesce(body, F.lit("")).cast("binary"))).alias("digest"), body.alias("body"))
    return rows.mapInArrow(judge, f"row_key {kind}, digest binary, n_words bigint, spans array<struct<start:bigint,end:bigint>>, items array<string>")


def contamination(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text",
                  item_col: str = "item_id", item_text_col: str = "text") -> DataFrame:
    """One row per document: n_words, n_hit, n_items, items (sorted ids), contaminated. No text is shuffled."""
    ready, blocks = _prepared(docs, benchmark, text_col, item_col, item_text_col)
    found = _judged(docs, _sent(ready, blocks - 1), True, id_col, text_col)
    if blocks > 1:
        earlier = None
        for block in range(blocks - 1):
            sent = _sent(ready, block)
            hits = settle(_judged(docs, sent, False, id_col, text_col), "hits")
            earlier = hits if earlier is None else earlier.union(hits)
            if sent is not None:
                sent.destroy()
        merged = earlier.groupBy(F.col("row_key").alias("_key"), F.col("digest").alias("_digest")).agg(
            F.flatten(F.collect_set("spans")).alias("more_spans"), F.array_distinct(F.flatten(F.collect_set("items"))).alias("more_items"))
        found = found.join(merged, F.col("row_key").eqNullSafe(F.col("_key")) & (F.col("digest") == F.col("_digest")), "left")
        found = found.withColumn("spans", F.array_sort(F.concat("spans", F.coalesce("more_spans", F.expr("cast(array() as array<struct<start:bigint,end:bigint>>)")))))
        found = found.withColumn("items", F.array_sort(F.array_union("items", F.coalesce("more_items", F.expr("cast(array() as array<string>)")))))
    start = F.struct(F.lit(0).cast("bigint").alias("upto"), F.lit(0).cast("bigint").alias("n"))
    hit = F.aggregate("spans", start, lambda s, x: F.struct(F.greatest(s["upto"], x["end"]).alias("upto"), (s["n"] + F.greatest(F.lit(0).cast("bigint"), x["end"] - F.greatest(s["upto"], x["start"]))).alias("n")), lambda s: s["n"])
    return found.withColumn("n_hit", hit).select(
        F.col("row_key").alias(id_col), "digest", "n_words", "n_hit", F.size("items").cast("bigint").alias("n_items"), "items",
        ((F.col("n_hit") > 0) & (F.col("n_hit") * 20 >= F.col("n_words"))).alias("contaminated"))


def remove_contaminated(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id",
                        item_text_col: str = "text") -> DataFrame:
    """The documents that are not contaminated, with all their columns.

    Contaminated rows are known by id and text together; they are settled first and, being few, usually broadcast.
    """
    bad = contamination(docs, benchmark, id_col, text_col, item_col, item_text_col).filter("contaminated")
    bad = settle(bad.select(F.col(id_col).alias("_bad_key"), F.col("digest").alias("_bad_digest")).distinct(), "contaminated")
    digest = F.unhex(F.md5(F.coalesce(docs[text_col].cast("string"), F.lit("")).cast("binary")))
    return docs.join(bad, docs[id_col].eqNullSafe(bad["_bad_key"]) & (digest == bad["_bad_digest"]), "left_anti")


def op7_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = contamination(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
    return found.withColumn("items_sha256", F.sha2(F.concat_ws(",", "items"), 256)).drop("items", "digest")


OP7_SQL = r"""
WITH item_words AS (
  SELECT item_id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w
  FROM benchmark WHERE text IS NOT NULL),
windows AS (
  SELECT DISTINCT item_id, least(13, len(w)) AS size, array_to_string(w[i : i + least(13, len(w)) - 1], ' ') AS body
  FROM (SELECT item_id, w, unnest(generate_series(1, greatest(1, len(w) - 12))) AS i FROM item_words WHERE len(w) > 0)),
doc_words AS (
  SELECT doc_id, coalesce(regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+'), []) AS w
  FROM documents),
sizes AS (SELECT DISTINCT size FROM windows),
spots AS (
  SELECT doc_id, size, i, array_to_string(w[i : i + size - 1], ' ') AS body
  FROM (SELECT doc_id, size, w, unnest(generate_series(1, len(w) - size + 1)) AS i FROM doc_words, sizes WHERE len(w) >= size)),
hits AS (SELECT doc_id, item_id, i, s.size FROM spots s JOIN windows b USING (size, body)),
covered AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(generate_series(i, i + size - 1)) AS p FROM hits) GROUP BY 1),
named AS (SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS items
          FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS item FROM hits) GROUP BY 1)
SELECT d.doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
       sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated
FROM doc_words d LEFT JOIN covered USING (doc_id) LEFT JOIN named USING (doc_id)
"""
