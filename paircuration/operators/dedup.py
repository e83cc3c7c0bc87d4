"""Exact and near duplicates: normalised digests, token sets, MinHash, banded index, verification."""

from __future__ import annotations

import math
import random

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from paircuration.config import DedupConfig
from paircuration.operators import greedy
from paircuration.sources.scratch import discard, settle, settle_all

PRIME = (1 << 31) - 1
MAP, WIDE = 8, 32  # words of a parity map
SLOTS, LAST = 1 << 19, 3  # slots that count tokens; earlier tokens that a prefix row carries
PARTS, PART = 16, 4_000_000  # parts of a prefix join at most; rows of one of them, about
MOVED = 2_000_000  # signatures that one part of the buckets moves, about
COMMENTS = {
    "python": r"(?m)^\s*#[^\n]*|(\"{3}[^\"]*\"{3})",
    "other": r"/[*][^*]*[*]+(?:[^/*][^*]*[*]+)*/|(?m)//[^\n]*",
}


def normalise(code: Column, language: Column | None = None) -> Column:
    """Comments out (string literals survive), white space collapsed, ends trimmed."""
    if language is None:
        bare = code
    else:
        keep = r"(\"(?:[^\"\\\\\n]|\\\\.)*+\"|'(?:[^'\\\\\n]|\\\\.)*+')"
        hashed = F.regexp_replace(code, keep + r"|#[^\n]*", "$1")
        slashed = F.regexp_replace(code, keep + r"|//[^\n]*|/[*](?:[^*]|[*](?!/))*+[*]/", "$1")
        bare = F.when(language == "python", hashed).otherwise(slashed)
    return F.trim(F.regexp_replace(bare, r"\s+", " "))


def digest(text: Column, family: str = "md5") -> Column:
    return {"md5": F.md5, "sha2": lambda c: F.sha2(c, 256), "xxhash64": F.xxhash64}[family](text)


def exact(df: DataFrame, text: Column, order: list[str], family: str = "md5") -> DataFrame:
    """First row of each normalised text in the given order; exactly one row of each text stays.

    Only (digest, order) is aggregated: first rows come from a combined aggregate and return by a semi join.  A null text
    is a text of its own; rows whose order is null come last; of repeated rows, equal in digest and order, one stays.
    """
    mark = "digest of " + " ".join(df.columns)  # a name that no column has
    keyed = df.withColumn(mark, F.coalesce(digest(text, family).cast("string"), F.lit("null")))
    per = keyed.groupBy(F.col(f"`{mark}`").alias("_digest"), *[F.col(c).alias(f"_{i}") for i, c in enumerate(order)]).agg(F.count(F.lit(1)).alias("_n"))
    place = [x for i in range(len(order)) for x in (F.col(f"_{i}").isNull().alias(f"none{i}"), F.col(f"_{i}").alias(f"at{i}"))]
    first = per.groupBy("_digest").agg(F.min(F.struct(*place, F.col("_n").alias("n"))).alias("_first"))

    def kept(chosen: DataFrame) -> DataFrame:
        same = keyed[mark] == chosen["_digest"]
        for i, c in enumerate(order):
            same = same & keyed[c].eqNullSafe(chosen[f"_first.at{i}"])
        return keyed.join(chosen, same, "left_semi")

    once, many = kept(first.filter("_first.n = 1")), kept(first.filter("_first.n > 1"))  # the rows' exchange is shared
    return once.union(many.dropDuplicates([mark, *order])).drop(mark)


def exact_confirmed(df: DataFrame, text: Column, order: list[str]) -> DataFrame:
    """Collision-safe: a fast digest routes, the text itself decides. Moves the texts."""
    keyed = df.withColumn("_digest", F.xxhash64(text)).withColumn("_text", text)
    rank = F.row_number().over(Window.partitionBy("_digest", "_text").orderBy(*order))
    return keyed.withColumn("_rank", rank).filter("_rank = 1").drop("_digest", "_text", "_rank")


def exact_report(df: DataFrame, text: Column, order: str, family: str = "md5") -> DataFrame:
    """(order key, dup_of, group_size) of every row: one combined aggregate, joined back on the digest."""
    keyed = df.select(order, digest(text, family).alias("_digest"))
    groups = keyed.groupBy("_digest").agg(F.min(order).alias("dup_of"), F.count(F.lit(1)).alias("group_size"))
    return keyed.join(groups, "_digest").select(order, "dup_of", "group_size")


def token_set(text: Column, pattern: str = "[a-z0-9_]+") -> Column:
    return F.array_distinct(F.regexp_extract_all(F.lower(text), F.lit(pattern), F.lit(0)))


def jaccard(a: Column, b: Column) -> Column:
    """Share of common tokens; two empty sets have 0."""
    common = F.size(F.array_intersect(a, b))
    return F.when(F.size(a) + F.size(b) == 0, 0.0).otherwise(common / (F.size(a) + F.size(b) - common))


def coefficients(cfg: DedupConfig) -> list[tuple[int, int]]:
    draw = random.Random(cfg.seed)
    return [(draw.randrange(1, PRIME), draw.randrange(PRIME)) for _ in range(cfg.num_hashes)]


def _affine_minima(values: np.ndarray, sizes: np.ndarray, pairs: np.ndarray) -> np.ndarray:
    """Minimum of (a v + b) mod 2^31 - 1 over each set's values (sets laid end to end, none empty), for all (a, b)."""
    out = np.full((len(sizes), len(pairs)), PRIME, dtype=np.uint64)
    owner, a, b = np.repeat(np.arange(len(sizes)), sizes), pairs[:, :1], pairs[:, 1:]
    prime, shift = np.uint64(PRIME), np.uint64(31)
    for at in range(0, len(values), 1024):
        x = a * values[None, at : at + 1024] + b  # below 2^63
        x = (x & prime) + (x >> shift)  # the modulus is a Mersenne prime: fold twice, subtract once
        x = (x & prime) + (x >> shift)
        x -= prime * (x >= prime)
        sets, first = np.unique(owner[at : at + 1024], return_index=True)
        out[sets] = np.minimum(out[sets], np.minimum.reduceat(x, first, axis=1).T)
    return out


def _parity_maps(values: np.ndarray, sizes: np.ndarray, words: int = MAP) -> np.ndarray:
    """64 * words bits of each set (sets laid end to end), as longs; each bit is the parity of the number of values that name it."""
    width = 64 * words
    at = np.repeat(np.arange(len(sizes)) * width, sizes) + (values % np.uint64(width)).astype(np.int64)
    odd = np.bincount(at, minlength=len(sizes) * width).astype(np.uint8) & 1
    return np.packbits(odd.reshape(len(sizes), width), axis=1, bitorder="little").view(np.int64)


def _slot_planes(minima: np.ndarray) -> np.ndarray:
    """The lowest two bits of every slot: one plane of longs for each, slots filled up with zeros to whole longs."""
    full = np.pad(minima, ((0, 0), (0, -minima.shape[1] % 64)))
    return np.hstack([np.packbits((full >> np.uint64(i) & np.uint64(1)).astype(np.uint8), axis=1, bitorder="little").view(np.int64) for i in range(2)])


def _affine_signatures(sets: DataFrame, id_col: str, cfg: DedupConfig, mapped: bool = False) -> DataFrame:
    """`sets` has (id, tokens); tokens are digested in the JVM, so only integers reach the array arithmetic.

    With `mapped`, `bits` has what bounds the similarity of two rows from above: see `bound`.
    """
    kind, pairs = sets.schema[id_col].dataType.simpleString(), np.array(coefficients(cfg), dtype=np.uint64)

    def run(batches):
        for batch in batches:
            batch = batch.filter(pc.greater(pc.fill_null(pc.list_value_length(batch.column(1)), 0), 0))
            for at in range(0, len(batch), 512):
                part = batch.slice(at, 512)
                sizes = pc.list_value_length(part.column(1)).to_numpy().astype(np.int64)
                values = pc.list_flatten(part.column(1)).to_numpy().astype(np.uint64)
                found = _affine_minima(values, sizes, pairs)
                made = {"row_key": part.column(0), "n_tokens": pa.array(sizes), "signature": lists(found.astype(np.int64))}
                if mapped:
                    made["bits"] = lists(_slot_planes(found) if cfg.verify == "signature" else _parity_maps(values, sizes))
                yield pa.record_batch(list(made.values()), names=list(made))

    def lists(rows):
        ends = pa.array(np.arange(len(rows) + 1) * rows.shape[1], pa.int32())
        return pa.ListArray.from_arrays(ends, pa.array(rows.ravel()))

    def value(token):
        return F.conv(F.substring(F.md5(token), 1, 8), 16, 10).cast("bigint").bitwiseAND(F.lit(PRIME))

    values = sets.select(F.col(id_col).alias("row_key"), F.transform("tokens", value).alias("values"))
    found = values.mapInArrow(run, f"row_key {kind}, n_tokens bigint, signature array<bigint>" + ", bits array<bigint>" * mapped)
    return found.withColumnRenamed("row_key", id_col)


def signatures(df: DataFrame, id_col: str, text: Column, cfg: DedupConfig = DedupConfig()) -> DataFrame:
    """(id, n_tokens, signature): minima of k hashes over the token set.

    The affine family is narrow: sets are made in the JVM and their minima by array arithmetic, batch by batch, so tokens
    never move.  The xxhash64 family explodes the tokens and takes all minima in one aggregate.  Rows without tokens have
    no signature and never pair; ids are taken to be unique.
    """
    if cfg.family == "affine31":
        return _affine_signatures(df.select(id_col, token_set(text).alias("tokens")), id_col, cfg)
    tokens = df.select(id_col, F.explode(token_set(text)).alias("token"))
    slots = [F.min(F.xxhash64(F.lit(cfg.seed + i), "token")).alias(f"h{i}") for i in range(cfg.num_hashes)]
    grouped = tokens.groupBy(id_col).agg(F.count(F.lit(1)).alias("n_tokens"), *slots)
    return grouped.select(id_col, "n_tokens", F.array(*[f"h{i}" for i in range(cfg.num_hashes)]).alias("signature"))


def estimate(a: Column, b: Column) -> Column:
    """Share of equal slots."""
    return F.size(F.filter(F.zip_with(a, b, lambda x, y: x == y), lambda e: e)) / F.size(a)


def similarity_cells(sizes: DataFrame, n: int = 200) -> list[float]:
    """Share of sets' weight in each of n equal ranges of similarity; `sizes` has (size, sets).

    A set weighs 1, in equal parts over the similarities that it can have to sets of its own size, one for each number of
    common tokens.  Empty sets pair with nothing and weigh nothing.
    """
    flat = sizes.filter("size > 0").select("sets", "size", F.explode(F.sequence(F.lit(0), F.col("size"))).alias("c"))
    cell = F.least(F.lit(n - 1), F.expr(f"{n} * c div (2 * size - c)"))
    found = {r["cell"]: r["w"] for r in flat.groupBy(cell.cast("int").alias("cell")).agg(F.sum(F.col("sets") / (F.col("size") + 1)).alias("w")).collect()}
    return [found.get(i, 0.0) for i in range(n)]


def choose_bands(tau: float, k: int, w_fp: float = 0.5, w_fn: float = 0.5, cells: list[float] | None = None) -> tuple[int, int]:
    """(bands, rows) with the least weighted area of wrong answers around the threshold.

    With `cells`, the weights of equal ranges of similarity, answers count by those instead of evenly on either side.
    """
    def area(b, r, low, high):
        n = 200
        step = (high - low) / n
        curve = lambda s: 1 - (1 - s**r) ** b
        wrong = (lambda s: 1 - curve(s)) if low >= tau else curve
        return sum(wrong(low + (i + 0.5) * step) for i in range(n)) * step

    def weighed(b, r):
        total = 0.0
        for i, w in enumerate(cells):
            miss = (1 - ((i + 0.5) / len(cells)) ** r) ** b
            total += w * (w_fp * (1 - miss) if i < round(tau * len(cells)) else w_fn * miss)
        return total

    options = [(b, r) for r in range(1, k + 1) for b in range(1, k // r + 1)]
    if cells is not None:
        return min(options, key=lambda o: (weighed(*o), o))
    return min(options, key=lambda o: (w_fp * area(*o, 0.0, tau) + w_fn * area(*o, tau, 1.0), o))


def index(sigs: DataFrame, id_col: str, cfg: DedupConfig = DedupConfig(), scope: str | None = None) -> DataFrame:
    """(band, key, id): one row per band; no shuffle.  With a scope column, only rows of one scope can share a key."""
    within = F.concat(F.coalesce(F.col(scope).cast("string"), F.lit("")), F.lit("\n")) if scope else F.lit("")
    bands = [F.md5(F.concat(within, F.array_join(F.slice("signature", i * cfg.rows + 1, cfg.rows).cast("array<string>"), ","))) for i in range(cfg.bands)]
    return sigs.select(F.posexplode(F.array(*bands)).alias("band", "key"), F.col(id_col))


def candidates(idx: DataFrame, id_col: str) -> DataFrame:
    """Distinct (lo, hi) pairs that share a bucket, by an equi-join on (band, key).

    Exact copies are gone before this step, so buckets hold near copies only; AQE splits skewed ones.  Where buckets
    alone decide, `greedy.resolve_buckets` needs no pairs at all and is linear in the index.
    """
    a, b = idx.withColumnRenamed(id_col, "lo"), idx.withColumnRenamed(id_col, "hi")
    return a.join(b, ["band", "key"]).filter("lo < hi").select("lo", "hi").distinct()


def profiles(df: DataFrame, id_col: str, text: Column, cfg: DedupConfig = DedupConfig(), scope: str | None = None) -> DataFrame:
    """(id, n, b0, b1, ..., keys): one narrow row per set, with its bucket keys and what bounds similarities from above.

    Keys are 64-bit hashes of band and slots: an accidental meeting is one more candidate for the verification.  The other
    family than the affine one takes its bounds from the parity maps, so only for exact verification.
    """
    sigs = _affine_signatures(df.select(id_col, token_set(text).alias("tokens")), id_col, cfg, mapped=True)
    if cfg.family != "affine31":
        sigs = sigs.drop("signature").join(signatures(df, id_col, text, cfg).select(id_col, "signature"), id_col)
    rows = _profiled(sigs, id_col, cfg)
    if scope:
        rows = rows.join(df.select(id_col, F.coalesce(F.col(scope).cast("string"), F.lit("")).alias("_scope")), id_col)
        rows = rows.withColumn("keys", F.transform("keys", lambda k: F.xxhash64("_scope", k))).drop("_scope")
    return rows


def set_profiles(sets: DataFrame, id_col: str, cfg: DedupConfig = DedupConfig()) -> DataFrame:
    """The profiles of (id, tokens), by the affine family."""
    return _profiled(_affine_signatures(sets.select(id_col, "tokens"), id_col, cfg, mapped=True), id_col, cfg)


def _profiled(sigs: DataFrame, id_col: str, cfg: DedupConfig) -> DataFrame:
    keys = F.array(*[F.xxhash64(F.lit(i), F.slice("signature", i * cfg.rows + 1, cfg.rows)) for i in range(cfg.bands)])
    words = 2 * (-(-cfg.num_hashes // 64)) if cfg.verify == "signature" else MAP
    return sigs.select(id_col, F.col("n_tokens").cast("int").alias("n"), *[F.col("bits")[i].alias(f"b{i}") for i in range(words)], keys.alias("keys"))


def bounded_index(rows: DataFrame, id_col: str, shared: DataFrame | None = None) -> DataFrame:
    """(key, id, n, b0, b1, ...) of the profiles' rows in every bucket of two or more; the others meet nothing and are left behind.

    `shared` names other buckets to take, each once: those that meet another index.
    """
    flat = rows.select(F.explode("keys").alias("key"), id_col)
    if shared is None:
        shared = settle(flat.groupBy("key").agg(F.count(F.lit(1)).alias("members")).filter("members > 1").select("key"), "shared")
    members = settle(flat.join(shared.hint("merge"), "key", "left_semi"), "members")
    return members.join(rows.drop("keys"), id_col).select("key", id_col, *[c for c in rows.columns if c not in (id_col, "keys")])


def bound(words: int, cfg: DedupConfig) -> str:
    """Condition on index rows x and y that no pair at the threshold fails.

    Exact: sizes, and no fewer tokens differ than bits of the two parity maps.  Signature: slots differ where one of
    their two lowest bits does.
    """
    if cfg.verify == "signature":
        half = words // 2
        differ = " + ".join(f"bit_count((x.b{i} ^ y.b{i}) | (x.b{half + i} ^ y.b{half + i}))" for i in range(half))
        return f"{differ} <= {int(cfg.num_hashes * (1 - cfg.tau_lsh) + 1e-6)}"
    differ = " + ".join(f"bit_count(x.b{i} ^ y.b{i})" for i in range(words))
    most = (1 - cfg.tau_lsh) / (1 + cfg.tau_lsh)
    return f"least(x.n, y.n) >= {cfg.tau_lsh!r}D * greatest(x.n, y.n) - 1e-6D AND {differ} <= {most!r}D * (x.n + y.n) + 1e-6D"


def bounded_candidates(first: DataFrame, second: DataFrame, id_col: str, cfg: DedupConfig = DedupConfig(), ordered: bool = True) -> DataFrame:
    """Distinct (lo, hi) of rows of two bounded indexes that share a bucket, without the pairs whose bound lies below the threshold.

    The bound is part of the join's condition, so rows that only share a bucket make no row of their own, and no feature
    is moved for them.
    """
    words = len([c for c in first.columns if c[:1] == "b" and c[1:].isdigit()])
    on = F.expr(f"x.key = y.key AND {bound(words, cfg)}" + f" AND x.`{id_col}` < y.`{id_col}`" * ordered)
    met = first.alias("x").join(second.alias("y").hint("merge"), on)
    return met.select(F.col(f"x.{id_col}").alias("lo"), F.col(f"y.{id_col}").alias("hi")).distinct()


def _meet(docs: pa.Table, pairs: pa.Table, mode: str, tau: float) -> pa.Table:
    """Similar pairs of one group; `docs` has (id, feature), tokens as sorted distinct longs or slots of a signature."""
    flat, found = docs["feature"].combine_chunks(), np.empty(len(pairs))
    values, ends = flat.flatten().to_numpy(zero_copy_only=False), np.concatenate([[0], np.cumsum(pc.list_value_length(flat).to_numpy(zero_copy_only=False))])
    places = [pc.index_in(pairs[c], value_set=docs["id"].combine_chunks()).to_numpy() for c in ("lo", "hi")]
    for k, at in enumerate(zip(*places)):
        a, b = (values[ends[x] : ends[x + 1]] for x in at)
        if mode == "signature":
            sim = int((a == b).sum()) / len(a)
        else:
            common = len(np.intersect1d(a, b, assume_unique=True))
            union = len(a) + len(b) - common
            sim = (common if 100 * common >= tau * union else -1) if mode == "common" else common / union
        found[k] = sim
    return pairs.select(["lo", "hi"]).append_column("sim", pa.array(found)).filter(pa.array(found >= (0 if mode == "common" else tau)))


def verify_grouped(pairs: DataFrame, features: DataFrame, id_col: str, mode: str, tau: float, block: int = 4096) -> DataFrame:
    """(lo, hi, sim) with sim >= tau; a feature moves once for its component of candidate pairs, not once for each pair.

    Components share groups of about `block` rows.  A larger one is dealt into blocks and every two of them are a group,
    so no group grows with a component.  `features` has the signature, or the tokens, which are compared by 64-bit hashes.
    In the mode "common", tau is in percent, compared in integers, and sim is the number of common tokens.
    """
    kind, column = pairs.schema["lo"].dataType.simpleString(), "signature" if mode == "signature" else "tokens"
    nodes = settle(greedy.components_keep_first(pairs).select("id", "root"), "nodes")
    groups = max(1, -(-nodes.count() // block))
    sizes = settle(nodes.groupBy("root").agg(F.ceil(F.count(F.lit(1)) / block).cast("int").alias("k")), "sizes")
    slot = F.when(F.col("k") == 1, F.pmod(F.xxhash64("root"), F.lit(groups))).otherwise(-1 - F.pmod(F.xxhash64("root"), F.lit(1 << 40)))
    placed = nodes.join(sizes.hint("merge"), "root").select("id", slot.alias("slot"), "k", F.pmod(F.xxhash64("id", F.lit(1)), "k").cast("int").alias("block"))
    placed = settle(placed, "placed")
    discard(nodes, sizes)
    sent = placed.select("id", "slot", "block", F.explode(F.sequence(F.lit(0), F.col("k") - 1)).alias("other"))
    sent = sent.select("id", "slot", F.least("block", "other").alias("first"), F.greatest("block", "other").alias("second"))
    value = F.col(column) if mode == "signature" else F.transform(column, lambda t: F.xxhash64(t))
    docs = features.select(F.col(id_col).alias("id"), value.alias("feature")).join(sent, "id")
    near, far = placed.select(F.col("id").alias("lo"), "slot", F.col("block").alias("x")).withColumnRenamed("slot", "_slot"), placed.select(F.col("id").alias("hi"), F.col("block").alias("y"))
    dealt = pairs.join(near, "lo").join(far, "hi").select("lo", "hi", F.col("_slot").alias("slot"), F.least("x", "y").alias("first"), F.greatest("x", "y").alias("second"))
    key = ["slot", "first", "second"]
    return docs.groupBy(*key).cogroup(dealt.groupBy(*key)).applyInArrow(lambda a, b: _meet(a, b, mode, tau), f"lo {kind}, hi {kind}, sim double")


def _bounded_meet(rows: pa.Table, tau: float, chunk: int = 32768) -> pa.Table:
    """(lo, hi) of one group of bucket members: pairs of a bucket that sizes and parity maps do not rule out."""
    rows = rows.sort_by([("key", "ascending"), ("n", "ascending")])
    sizes, block, (_, bucket) = rows["n"].to_numpy().astype(np.int64), rows["block"].to_numpy(), np.unique(rows["key"].to_numpy(), return_inverse=True)
    maps, rank = [rows[f"b{i}"].to_numpy().view(np.uint64) for i in range(MAP)], pc.rank(rows["id"], tiebreaker="dense").to_numpy()
    across, wide = rows["first"][0].as_py() != rows["second"][0].as_py(), int(sizes.max()) + 1
    last = bucket * wide + np.minimum((sizes / tau + 1e-5).astype(np.int64), wide - 1)  # the largest size that a row's size allows
    later = np.searchsorted(bucket * wide + sizes, last, side="right") - np.arange(len(rows)) - 1
    ends, most, found = np.cumsum(later), (1 - tau) / (1 + tau), [(np.empty(0, np.int64), np.empty(0, np.int64))]
    for at in range(0, int(ends[-1]), chunk):  # pairs are numbered by their smaller row
        n = np.arange(at, min(at + chunk, int(ends[-1])))
        i = np.searchsorted(ends, n, side="right")
        j = i + 1 + n - (ends - later)[i]
        if across:  # what lies in one block meets where the block meets itself
            apart = block[i] != block[j]
            i, j = i[apart], j[apart]
        differ, room = np.zeros(len(i), np.int64), most * (sizes[i] + sizes[j]) + 1e-6
        for k in range(0, MAP, 4):
            for m in maps[k : k + 4]:
                differ += np.bitwise_count(m[i] ^ m[j])
            near = differ <= room
            i, j, differ, room = i[near], j[near], differ[near], room[near]
        found.append((i, j))
    i, j = (np.concatenate(x) for x in zip(*found))
    i, j = i[rank[i] != rank[j]], j[rank[i] != rank[j]]
    swap = rank[i] > rank[j]
    return pa.table({"lo": rows["id"].take(pa.array(np.where(swap, j, i))), "hi": rows["id"].take(pa.array(np.where(swap, i, j)))})


def bounded_meetings(made: DataFrame, id_col: str, tau: float, block: int = 16384) -> DataFrame:
    """Distinct (lo, hi) of profiles that share a bucket, without the pairs whose bound (see `bound`, exact) lies below tau.

    For buckets that are common, as those of single hashes: a bucket's rows are put in order by size and only those near in
    size are compared, as arrays.
    """
    kind = made.schema[id_col].dataType.simpleString()
    rows = made.withColumnRenamed(id_col, "id")
    flat = rows.select(F.explode("keys").alias("key"), "id")
    shared = settle(flat.groupBy("key").agg(F.count(F.lit(1)).alias("members")).filter("members > 1"), "shared")
    groups = max(1, -(-shared.agg(F.coalesce(F.sum("members"), F.lit(0))).first()[0] // block))
    sent = _sent(flat.join(shared.hint("merge"), "key"), block, groups).join(rows.drop("keys").hint("merge"), "id")
    return sent.groupBy("slot", "first", "second").applyInArrow(lambda t: _bounded_meet(t, tau), f"lo {kind}, hi {kind}").distinct()


def _estimates(rows: pa.Table, cfg: DedupConfig, chunk: int = 4096) -> pa.Table:
    """(lo, hi, sim) of one group of bucket members: pairs that share a bucket, each only in the first band that it shares."""
    rows = rows.sort_by([("key", "ascending"), ("id", "ascending")])
    keys, band, block = (rows[c].to_numpy() for c in ("key", "band", "block"))
    slots = rows["signature"].combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(len(rows), cfg.num_hashes)
    later = np.searchsorted(keys, keys, side="right") - np.arange(len(rows)) - 1
    across = rows["first"][0].as_py() != rows["second"][0].as_py()
    ends, found = np.cumsum(later), [(np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0))]
    for at in range(0, int(ends[-1]), chunk):  # pairs are numbered by their first row
        n = np.arange(at, min(at + chunk, int(ends[-1])))
        i = np.searchsorted(ends, n, side="right")
        j = i + 1 + n - (ends - later)[i]
        if across:  # what lies in one block is paired where the block meets itself
            apart = block[i] != block[j]
            i, j = i[apart], j[apart]
        equal = slots[i] == slots[j]
        bands = equal[:, : cfg.bands * cfg.rows].reshape(len(i), cfg.bands, cfg.rows)
        shared = bands[:, :, 0].copy()
        for r in range(1, cfg.rows):
            shared &= bands[:, :, r]
        mine = shared[np.arange(len(i)), band[i]] & (shared.argmax(axis=1) == band[i])
        found.append((i[mine], j[mine], equal[mine].sum(axis=1) / cfg.num_hashes))
    i, j, sims = (np.concatenate(x) for x in zip(*found))
    return pa.table({"lo": rows["id"].take(pa.array(i)), "hi": rows["id"].take(pa.array(j)), "sim": pa.array(sims)})


def _sent(members: DataFrame, block: int, groups: int) -> DataFrame:
    """Buckets' rows, once for each group (slot, first, second) that takes them; `members` is the size of a row's bucket.

    Buckets share `groups` groups; one of more than `block` rows is dealt into blocks and every two of them are a group.
    """
    k = F.ceil(F.col("members") / block).cast("int")
    slot = F.when(F.col("members") <= block, F.pmod(F.xxhash64("key"), F.lit(groups))).otherwise(-1 - F.pmod(F.xxhash64("key"), F.lit(1 << 40)))
    dealt = members.withColumn("slot", slot).withColumn("block", F.pmod(F.xxhash64("id", F.lit(1)), k).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), k - 1)))
    return dealt.withColumn("first", F.least("block", "other")).withColumn("second", F.greatest("block", "other")).drop("members", "other")


def bucket_estimates(sigs: DataFrame, id_col: str, cfg: DedupConfig = DedupConfig(), block: int = 1024, most: int = 500_000) -> DataFrame:
    """(lo, hi, sim) of all pairs that share a bucket, with their share of equal slots.

    Pairs are made where a bucket's signatures are, and put out once, so no table of pairs is shuffled, made distinct or
    searched for components.  A signature moves once for each bucket that it shares.  Buckets lie in groups of about
    4 * `block` rows or `most` pairs; one of more than `block` rows is dealt into blocks and every two of them are a group.
    Slots are compared themselves, so keys that meet by accident make no pair.  Where many signatures move, the buckets are
    taken in up to 16 parts one after the other, so disk holds the signatures of one part at a time.
    """
    kind = sigs.schema[id_col].dataType.simpleString()
    keys = F.array(*[F.xxhash64(F.lit(i), F.slice("signature", i * cfg.rows + 1, cfg.rows)) for i in range(cfg.bands)])
    flat = sigs.select(F.posexplode(keys).alias("band", "key"), F.col(id_col).alias("id"))
    shared = settle(flat.groupBy("key").agg(F.count(F.lit(1)).alias("n")).filter("n > 1"), "shared")
    rows, pairs = shared.agg(F.coalesce(F.sum("n"), F.lit(0)), F.coalesce(F.sum(F.expr("n * (n - 1) div 2")), F.lit(0))).first()
    groups = max(1, -(-rows // (4 * block)), -(-pairs // most))
    members = settle(flat.join(shared.hint("merge"), "key").withColumnRenamed("n", "members"), "members")
    discard(shared)
    sent = _sent(members, block, groups)
    narrow = F.col("signature").cast("array<int>") if cfg.family == "affine31" else F.col("signature")  # minima below 2^31
    slots = sigs.select(F.col(id_col).alias("id"), narrow.alias("signature")).hint("merge")
    parts = min(PARTS, max(1, -(-rows // MOVED)))

    def met(part: int) -> DataFrame:
        mine = sent.filter(F.pmod("key", F.lit(parts)) == part).join(slots, "id")
        return mine.groupBy("slot", "first", "second").applyInArrow(lambda t: _estimates(t, cfg), f"lo {kind}, hi {kind}, sim double")

    return met(0) if parts == 1 else settle_all((met(i) for i in range(parts)), "estimates")


def bucket_report(idx: DataFrame) -> DataFrame:
    """Bucket sizes and how many buckets have each: tells which pass to use."""
    return idx.groupBy("band", "key").agg(F.count(F.lit(1)).alias("members")).groupBy("members").agg(F.count(F.lit(1)).alias("buckets"))


def verify(pairs: DataFrame, features: DataFrame, id_col: str, mode: str, tau: float) -> DataFrame:
    """(lo, hi, sim) with sim >= tau. `features` has the signature, or the token array for the exact mode."""
    if mode == "none":
        return pairs.withColumn("sim", F.lit(None).cast("double"))
    column = "signature" if mode == "signature" else "tokens"
    a = features.select(F.col(id_col).alias("lo"), F.col(column).alias("_a"))
    b = features.select(F.col(id_col).alias("hi"), F.col(column).alias("_b"))
    sim = estimate(F.col("_a"), F.col("_b")) if mode == "signature" else jaccard(F.col("_a"), F.col("_b"))
    return pairs.join(a, "lo").join(b, "hi").withColumn("sim", sim).filter(F.col("sim") >= tau).select("lo", "hi", "sim")


def _wide_maps(batches):
    for batch in batches:
        for at in range(0, len(batch), 512):
            part = batch.slice(at, 512)
            sizes = pc.list_value_length(part.column(1)).to_numpy().astype(np.int64)
            maps = _parity_maps(pc.list_flatten(part.column(1)).to_numpy().view(np.uint64), sizes, WIDE)
            yield pa.record_batch([part.column(0), pa.array(sizes), pa.array([x.tobytes() for x in maps], pa.binary())], names=["id", "n", "bits"])


def _close_pairs(table: pa.Table, tau_percent: int) -> pa.Table:
    """Pairs (a, b) of one pair of blocks, or of one block, that sizes and parity maps do not rule out."""
    if not len(table):
        return pa.table({"a": table["id"], "b": table["id"]})
    here = [table[c][0].as_py() for c in ("c1", "b1", "c2", "b2")]
    ids, sizes = table["id"].to_numpy(), table["n"].to_numpy()
    maps = np.frombuffer(b"".join(table["bits"].to_pylist()), np.uint64).reshape(len(table), WIDE)
    order = np.argsort(sizes, kind="stable")
    first = (table["c"].to_numpy() == here[0]) & (table["b"].to_numpy() == here[1])
    alone = here[:2] == here[2:]
    left, right = order[first[order]], order if alone else order[~first[order]]
    head, tail, widths, found = np.ascontiguousarray(maps[right, :MAP]), maps[right, MAP:], sizes[right], []
    for i, x in enumerate(left.tolist()):
        n = int(sizes[x])
        at, to = np.searchsorted(widths, [-(-tau_percent * n // 100), 100 * n // tau_percent + 1])
        at = max(at, i + 1) if alone else at
        most = (100 - tau_percent) * (n + widths[at:to])
        differ = np.bitwise_count(head[at:to] ^ maps[x, :MAP]).sum(axis=1, dtype=np.int64)
        left_in = np.flatnonzero((100 + tau_percent) * differ <= most)
        differ = differ[left_in] + np.bitwise_count(tail[at:to][left_in] ^ maps[x, MAP:]).sum(axis=1, dtype=np.int64)
        left_in = left_in[(100 + tau_percent) * differ <= most[left_in]]
        found.append((np.full(len(left_in), x), right[at + left_in]))
    a, b = (np.concatenate([f[k] for f in found]) if found else np.empty(0, np.int64) for k in range(2))
    return pa.table({"a": table["id"].take(pa.array(a)), "b": table["id"].take(pa.array(b))})


def all_pairs(sets: DataFrame, id_col: str, tau_percent: int, block: int = 8192) -> DataFrame:
    """Every pair with Jaccard >= tau, by comparing all pairs whose sizes allow it: the quadratic reference.

    Sets are classed by size, so a pair lies in one class or two neighbouring ones, and a class is dealt into blocks.  Each two
    blocks meet once, as sizes and parity maps; what those cannot rule out is compared whole, so no token is ever joined and no
    row is made for an unlike pair.  Integer arithmetic: 100 * common >= tau * union.
    """
    kind = sets.schema[id_col].dataType.simpleString()
    sets = settle(sets.filter(F.size("tokens") > 0), "sets")
    hashed = sets.select(F.col(id_col).alias("id"), F.transform("tokens", lambda t: F.xxhash64(t)).alias("values"))
    rows = settle(hashed.mapInArrow(_wide_maps, f"id {kind}, n bigint, bits binary"), "maps")
    rows = rows.withColumn("c", F.floor(F.log("n") / (math.log(100 / tau_percent) + 1e-9)).cast("int"))  # above the ratio: classes differ by one at most
    per = settle(rows.groupBy("c").agg(F.ceil(F.count(F.lit(1)) / block).cast("int").alias("k")), "classes")
    near = per.alias("x").join(per.alias("y"), F.expr("abs(x.c - y.c) <= 1")).select(F.col("x.c").alias("c"), F.col("y.c").alias("oc"), F.col("x.k").alias("k"), F.col("y.k").alias("ok"))
    sent = rows.join(F.broadcast(near), "c").withColumn("b", F.pmod(F.xxhash64("id"), "k").cast("int"))
    sent = sent.select("id", "n", "bits", "c", "b", "oc", F.explode(F.sequence(F.lit(0), F.col("ok") - 1)).alias("ob"))
    swap = F.expr("oc < c OR oc = c AND ob < b")
    key = [F.when(swap, F.col(o)).otherwise(F.col(m)).alias(n) for n, m, o in (("c1", "c", "oc"), ("b1", "b", "ob"), ("c2", "oc", "c"), ("b2", "ob", "b"))]
    met = sent.select("id", "n", "bits", "c", "b", *key).groupBy("c1", "b1", "c2", "b2").applyInArrow(lambda t: _close_pairs(t, tau_percent), f"a {kind}, b {kind}")
    pairs = settle(met.select(F.least("a", "b").alias("lo"), F.greatest("a", "b").alias("hi")), "pairs")
    return verify_grouped(pairs, sets, id_col, "common", tau_percent).select("lo", "hi", F.col("sim").cast("bigint").alias("common"))


def _rarity(batches):
    counts = np.zeros(SLOTS, np.int64)
    for batch in batches:
        counts += np.bincount((pc.list_flatten(batch.column(0)).to_numpy().view(np.uint64) % np.uint64(SLOTS)).astype(np.int64), minlength=SLOTS)
    used = np.flatnonzero(counts)
    yield pa.record_batch([pa.array(used.astype(np.int32)), pa.array(counts[used])], names=["slot", "n"])


def _prefixes(counts, tau_percent: int):
    """Rows (id, n, rare, b0, ...): the rarest tokens of each set, in order; `counts` has how often each slot's tokens occur."""
    def run(batches):
        for batch in batches:
            for at in range(0, len(batch), 512):
                part = batch.slice(at, 512)
                sizes = pc.list_value_length(part.column(1)).to_numpy().astype(np.int64)
                values = pc.list_flatten(part.column(1)).to_numpy()
                owner = np.repeat(np.arange(len(sizes)), sizes)
                maps = _parity_maps(values.view(np.uint64), sizes)
                values = values[np.lexsort((values, counts.value[values.view(np.uint64) % np.uint64(SLOTS)], owner))]
                place = np.arange(len(values)) - np.repeat(np.cumsum(sizes) - sizes, sizes) + 1
                widths = sizes - -(-sizes * tau_percent // 100) + 1
                ends = pa.array(np.concatenate([[0], np.cumsum(widths)]), pa.int32())
                made = {"id": part.column(0), "n": pa.array(sizes.astype(np.int32)), "rare": pa.ListArray.from_arrays(ends, pa.array(values[place <= np.repeat(widths, sizes)]))}
                made |= {f"b{i}": pa.array(maps[:, i]) for i in range(MAP)}
                yield pa.record_batch(list(made.values()), names=list(made))

    return run


def prefix_join(sets: DataFrame, id_col: str, tau_percent: int) -> DataFrame:
    """Exact set-similarity join: the pairs that prefixes propose, verified whole, by groups."""
    pairs = prefix_pairs(sets, id_col, tau_percent)
    return verify_grouped(pairs, sets, id_col, "common", tau_percent).select("lo", "hi", F.col("sim").cast("bigint").alias("common"))


def prefix_pairs(sets: DataFrame, id_col: str, tau_percent: int, firsts: DataFrame | None = None) -> DataFrame:
    """Candidates (lo, hi), settled, among them all pairs with Jaccard >= tau: only the rarest tokens of each set, as many as a match must share one of, are joined.

    Sets are ordered by rarity; a prefix of n - ceil(tau n) + 1 tokens suffices.  Any order that all sets share is right, so
    rarity is counted by slots of token hashes and no token list is shuffled.  A pair is a row of the join only if sizes, parity
    maps and the tokens left after the shared one leave room for the similarity, and about once: a row carries the tokens
    before its own, and a pair that shares one of them has been put out there or earlier.

    Prefixes are settled once a set; rows with one token each exist only in the join's exchange.  Each token belongs to one
    of several parts, which are joined one after the other, so disk holds the exchange of one part at a time.
    With `firsts`, only the ids in it take part.
    """
    kind, spark = sets.schema[id_col].dataType.simpleString(), sets.sparkSession
    hashed = sets.filter(F.size("tokens") > 0).select(F.col(id_col).alias("id"), F.transform("tokens", lambda t: F.xxhash64(t)).alias("values"))
    counts = np.zeros(SLOTS, np.int64)
    for found in hashed.select("values").mapInArrow(_rarity, "slot int, n bigint").groupBy("slot").agg(F.sum("n").alias("n")).toArrow().to_batches():
        counts[found["slot"].to_numpy()] = found["n"].to_numpy()
    shape = f"id {kind}, n int, rare array<bigint>, " + ", ".join(f"b{i} bigint" for i in range(MAP))
    prefix = hashed.mapInArrow(_prefixes(spark.sparkContext.broadcast(counts), tau_percent), shape)
    if firsts is not None:
        prefix = prefix.join(firsts.select(F.col(id_col).alias("id")), "id", "left_semi")
    prefix = settle(prefix, "prefix")
    total = prefix.agg(F.coalesce(F.sum(F.size("rare")), F.lit(0))).first()[0]
    parts = min(PARTS, max(1, -(-total // PART)))
    flat = prefix.select("*", F.posexplode("rare").alias("at", "token"))
    earlier = [F.coalesce(F.get("rare", F.col("at") - k), F.lit(0)).alias(f"p{k}") for k in range(1, LAST + 1)]
    tau, differ = tau_percent, " + ".join(f"bit_count(x.b{i} ^ y.b{i})" for i in range(MAP))
    room = f"{100 + tau} * (1 + least(x.n - x.place, y.n - y.place)) >= {tau} * (x.n + y.n)"
    near = f"100 * least(x.n, y.n) >= {tau} * greatest(x.n, y.n) AND {100 + tau} * ({differ}) <= {100 - tau} * (x.n + y.n)"
    before = " OR ".join(f"x.p{i} = y.p{j} AND x.p{i} <> 0" for i in range(1, LAST + 1) for j in range(1, LAST + 1))
    on = F.expr(f"x.token = y.token AND x.id < y.id AND {room} AND {near} AND NOT ({before})")

    def met(part: int) -> DataFrame:
        rows = flat.filter(F.pmod("token", F.lit(parts)) == part).select("token", "id", "n", (F.col("at") + 1).alias("place"), *earlier, *[f"b{i}" for i in range(MAP)])
        return rows.alias("x").join(rows.alias("y").hint("merge"), on).select(F.col("x.id").alias("lo"), F.col("y.id").alias("hi")).distinct()

    if parts == 1:
        pairs = settle(met(0), "pairs")
    else:  # a pair can come from several parts
        found = settle_all((met(i) for i in range(parts)), "met")
        pairs = settle(found.distinct(), "pairs")
        discard(found)
    discard(prefix)
    return pairs
