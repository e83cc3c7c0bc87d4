"""Surrounding operators, sources and functions that users of the curation pipeline need, each with its SQL counterpart."""

from __future__ import annotations

import re
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from paircuration.operators import relational as R
from paircuration.sources import tables
from paircuration.sources.scratch import fresh
from paircuration.sources.tables import as_timestamp, load

QUERIES, ORACLES = {}, {}


def query(name: str, sql: str | None = None):
    def keep(fn):
        QUERIES[name] = fn
        if sql:
            ORACLES[name] = sql
        return fn
    return keep


def _n():
    return F.count(F.lit(1)).alias("n")


# ---- sources and sinks ----------------------------------------------------------------------------------------------


@query("scan_parquet", "SELECT doc_id, n_chars FROM documents WHERE n_chars BETWEEN 100 AND 2000")
def scan_parquet(spark, sf):
    return load(spark, sf, "documents").filter(F.col("n_chars").between(100, 2000)).select("doc_id", "n_chars")


_ROUND = "SELECT o_orderkey, o_custkey, o_orderstatus, o_totalprice FROM orders"


def _orders(spark, sf):
    return load(spark, sf, "orders", ["o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice"])


@query("roundtrip_json", _ROUND)
def roundtrip_json(spark, sf):
    rows, path = _orders(spark, sf), fresh(spark, "json")
    tables.write_jsonl(rows, path)
    return spark.read.schema(rows.schema).json(path)


@query("roundtrip_csv", _ROUND)
def roundtrip_csv(spark, sf):
    rows, path = _orders(spark, sf), fresh(spark, "csv")
    rows.write.csv(path, header=True)
    return spark.read.schema(rows.schema).csv(path, header=True)


@query("roundtrip_orc", _ROUND)
def roundtrip_orc(spark, sf):
    rows, path = _orders(spark, sf), fresh(spark, "orc")
    rows.write.orc(path)
    return spark.read.orc(path)


@query("roundtrip_partitioned", "SELECT doc_id, lang FROM documents WHERE lang = 'de'")
def roundtrip_partitioned(spark, sf):
    path = fresh(spark, "partitioned")
    tables.write_partitioned(load(spark, sf, "documents", ["doc_id", "lang"]), path, "lang")
    return spark.read.parquet(path).filter("lang = 'de'").select("doc_id", "lang")


@query("roundtrip_pairs_jsonl", "SELECT doc_id, length(text) AS prompt_chars FROM documents WHERE text IS NOT NULL")
def roundtrip_pairs_jsonl(spark, sf):
    path = fresh(spark, "pairs")
    tables.write_pairs(load(spark, sf, "documents").select("doc_id", F.col("text").alias("code"), F.col("lang").alias("doc")), path, "json")
    return spark.read.schema("doc_id bigint, prompt string, target string").json(path).select("doc_id", F.length("prompt").cast("bigint").alias("prompt_chars"))


@query("bucketed_join", "SELECT count(*) AS n, sum(l_quantity) AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE o_orderstatus = 'F'")
def bucketed_join(spark, sf):
    tag = fresh(spark, "b").rsplit("-", 1)[1][:10]
    tables.write_bucketed(load(spark, sf, "lineitem", ["l_orderkey", "l_quantity"]), f"lines_{tag}", "l_orderkey", 8)
    tables.write_bucketed(load(spark, sf, "orders", ["o_orderkey", "o_orderstatus"]), f"orders_{tag}", "o_orderkey", 8)
    lines, orders = spark.table(f"lines_{tag}"), spark.table(f"orders_{tag}").filter("o_orderstatus = 'F'")
    return lines.join(orders.hint("merge"), lines.l_orderkey == orders.o_orderkey).agg(_n(), F.sum("l_quantity").alias("quantity"))


@query("scan_text_lines")
def scan_text_lines(spark, sf):
    path = fresh(spark, "text")
    load(spark, sf, "pages", ["url"]).filter("url IS NOT NULL").write.text(path)
    return spark.read.text(path).agg(_n())


@query("source_tree_reader")
def source_tree_reader(spark, sf):
    from paircuration.sources.source_tree import SourceTree

    spark.dataSource.register(SourceTree)
    path = fresh(spark, "tree")
    load(spark, sf, "documents", ["text"]).write.text(path)
    return spark.read.format("source_tree").option("path", path).option("suffix", ".txt").load().select(F.length("source").alias("chars"), "language")


# ---- projection and filter ------------------------------------------------------------------------------------------

@query("filter_length", "SELECT doc_id FROM documents WHERE length(text) BETWEEN 20 AND 10000")
def filter_length(spark, sf):
    return load(spark, sf, "documents").filter(F.char_length("text").between(20, 10000)).select("doc_id")


@query("project_case", "SELECT c_custkey, CASE WHEN c_acctbal < 0 THEN 'debt' WHEN c_acctbal < 5000 THEN 'low' ELSE 'high' END AS band FROM customer")
def project_case(spark, sf):
    return load(spark, sf, "customer").select("c_custkey", F.when(F.col("c_acctbal") < 0, "debt").when(F.col("c_acctbal") < 5000, "low").otherwise("high").alias("band"))


@query("filter_regex", "SELECT doc_id FROM documents WHERE regexp_matches(text, '[0-9]{3}')")
def filter_regex(spark, sf):
    return load(spark, sf, "documents").filter(F.col("text").rlike("[0-9]{3}")).select("doc_id")


@query("null_safe_filter", "SELECT d.doc_id, l.toxic FROM documents d LEFT JOIN labels l USING (doc_id) WHERE l.toxic IS NOT DISTINCT FROM NULL OR l.toxic IN (1)")
def null_safe_filter(spark, sf):
    joined = load(spark, sf, "documents", ["doc_id"]).join(load(spark, sf, "labels"), "doc_id", "left")
    return joined.filter(F.col("toxic").eqNullSafe(F.lit(None)) | F.col("toxic").isin(1)).select("doc_id", "toxic")


# ---- equi joins -----------------------------------------------------------------------------------------------------

_JOINED = "SELECT c_mktsegment, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment"
for _name, _hint in (("join_broadcast", "broadcast"), ("join_sortmerge", "merge"), ("join_shuffle_hash", "shuffle_hash")):
    query(_name, _JOINED)(lambda spark, sf, h=_hint: load(spark, sf, "orders").join(load(spark, sf, "customer").hint(h), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(_n(), F.round(F.sum("o_totalprice"), 2).alias("total")))


def _doc_labels(how):
    def run(spark, sf):
        return load(spark, sf, "documents", ["doc_id", "lang"]).join(load(spark, sf, "labels", ["doc_id", "quality"]), "doc_id", how)
    return run


query("join_left", "SELECT doc_id, lang, quality FROM documents LEFT JOIN labels USING (doc_id)")(_doc_labels("left"))
query("join_semi", "SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")(_doc_labels("left_semi"))
query("join_anti", "SELECT doc_id, lang FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels WHERE doc_id IS NOT NULL)")(_doc_labels("left_anti"))


@query("join_full", "SELECT coalesce(c_custkey, o_custkey) AS custkey, count(o_orderkey) AS orders FROM customer FULL JOIN orders ON c_custkey = o_custkey GROUP BY 1")
def join_full(spark, sf):
    both = load(spark, sf, "customer", ["c_custkey"]).join(load(spark, sf, "orders", ["o_custkey", "o_orderkey"]), F.col("c_custkey") == F.col("o_custkey"), "full")
    return both.groupBy(F.coalesce("c_custkey", "o_custkey").alias("custkey")).agg(F.count("o_orderkey").alias("orders"))


@query("join_salted", "SELECT source, count(*) AS n FROM documents JOIN (SELECT DISTINCT source FROM documents) USING (source) GROUP BY source")
def join_salted(spark, sf):
    docs = load(spark, sf, "documents", ["doc_id", "source"])
    return R.salted_join(docs, docs.select("source").distinct(), "source", 8).groupBy("source").agg(_n())


# ---- other joins ----------------------------------------------------------------------------------------------------

@query("join_theta_size", "SELECT a.n_name AS a, b.n_name AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
def join_theta_size(spark, sf):
    n = load(spark, sf, "nation")
    a, b = n.select(F.col("n_nationkey").alias("ka"), F.col("n_name").alias("a"), F.col("n_regionkey").alias("r")), n.select(F.col("n_nationkey").alias("kb"), F.col("n_name").alias("b"), F.col("n_regionkey").alias("r"))
    return a.join(b, (a.r == b.r) & (a.ka < b.kb)).select("a", "b")


@query("join_range_band", "SELECT p_partkey, s.name FROM part JOIN (SELECT * FROM (VALUES ('small', 1, 15), ('middle', 16, 35), ('large', 36, 50)) t(name, low, high)) s ON p_size BETWEEN low AND high")
def join_range_band(spark, sf):
    bands = spark.createDataFrame([("small", 1, 15), ("middle", 16, 35), ("large", 36, 50)], "name string, low int, high int")
    return R.range_join(load(spark, sf, "part", ["p_partkey", "p_size"]), bands, "p_size", "low", "high", 8).select("p_partkey", "name")


_TEN = "INTERVAL 10 MINUTE"


@query("join_interval", f"SELECT a.event_id AS first_id, b.event_id AS later_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + {_TEN}")
def join_interval(spark, sf):
    e = as_timestamp(load(spark, sf, "events", ["event_id", "user_id", "ts"]), "ts")
    return R.interval_join(e, e, "user_id", "ts", 600).select(F.col("l.event_id").alias("first_id"), F.col("r.event_id").alias("later_id"))


@query("join_asof", "SELECT e.event_id, p.event_id AS purchase_id FROM events e ASOF LEFT JOIN (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY user_id, ts ORDER BY event_id DESC) AS rn FROM events WHERE event_type = 'purchase') WHERE rn = 1) p ON e.user_id = p.user_id AND e.ts >= p.ts WHERE e.event_type <> 'purchase'")
def join_asof(spark, sf):
    e = load(spark, sf, "events", ["event_id", "user_id", "ts", "event_type"])
    return R.asof_join(e.filter("event_type <> 'purchase'"), e.filter("event_type = 'purchase'"), "user_id", "ts", "event_id").select("event_id", F.col("found").alias("purchase_id"))


@query("join_self_bucket", "SELECT max(a.doc_id) AS lo, b.doc_id AS hi FROM documents a JOIN documents b ON a.lang = b.lang AND a.n_chars = b.n_chars AND md5(a.text) = md5(b.text) AND a.doc_id < b.doc_id GROUP BY b.doc_id")
def join_self_bucket(spark, sf):
    docs = load(spark, sf, "documents", ["doc_id", "lang", "n_chars", "text"])
    return R.bucket_pairs(docs.select("doc_id", "lang", "n_chars", F.md5("text").alias("digest")), ["lang", "n_chars", "digest"], "doc_id")


@query("join_cross", "SELECT r_name, n_name FROM region, nation")
def join_cross(spark, sf):
    return load(spark, sf, "nation", ["n_name"]).crossJoin(F.broadcast(load(spark, sf, "region", ["r_name"]))).select("r_name", "n_name")  # two fixed tables: 5 and 25 rows


# ---- aggregates -----------------------------------------------------------------------------------------------------

@query("agg_hash", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS quantity, round(avg(l_discount), 6) AS discount FROM lineitem GROUP BY ALL")
def agg_hash(spark, sf):
    return load(spark, sf, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(_n(), F.round(F.sum("l_quantity"), 2).alias("quantity"), F.round(F.avg("l_discount"), 6).alias("discount"))


@query("agg_sort", "SELECT o_custkey, array_to_string(list_sort(list(o_orderkey)), ',') AS orders FROM orders GROUP BY o_custkey")
def agg_sort(spark, sf):
    return load(spark, sf, "orders", ["o_custkey", "o_orderkey"]).groupBy("o_custkey").agg(F.array_join(F.array_sort(F.collect_list("o_orderkey")).cast("array<string>"), ",").alias("orders"))


@query("agg_distinct", "SELECT l_returnflag, count(DISTINCT l_orderkey) AS orders, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY l_returnflag")
def agg_distinct(spark, sf):
    return load(spark, sf, "lineitem", ["l_returnflag", "l_orderkey", "l_suppkey"]).groupBy("l_returnflag").agg(F.count_distinct("l_orderkey").alias("orders"), F.count_distinct("l_suppkey").alias("suppliers"))


@query("agg_approx_distinct")
def agg_approx_distinct(spark, sf):
    return load(spark, sf, "lineitem", ["l_returnflag", "l_orderkey"]).groupBy("l_returnflag").agg(F.approx_count_distinct("l_orderkey", 0.02).alias("orders"))


@query("agg_percentile", "SELECT l_returnflag, round(quantile_cont(l_extendedprice, 0.5), 4) AS median, round(quantile_cont(l_extendedprice, 0.9), 4) AS p90 FROM lineitem GROUP BY l_returnflag")
def agg_percentile(spark, sf):
    return load(spark, sf, "lineitem", ["l_returnflag", "l_extendedprice"]).groupBy("l_returnflag").agg(*[F.round(F.percentile("l_extendedprice", q), 4).alias(a) for q, a in ((0.5, "median"), (0.9, "p90"))])


@query("agg_min_by", "SELECT o_custkey, arg_min(o_orderkey, (o_totalprice, o_orderkey)) AS cheapest, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS dearest FROM orders GROUP BY o_custkey")
def agg_min_by(spark, sf):
    order = F.struct("o_totalprice", "o_orderkey")
    return load(spark, sf, "orders").groupBy("o_custkey").agg(F.min_by("o_orderkey", order).alias("cheapest"), F.max_by("o_orderkey", order).alias("dearest"))


@query("agg_filter_clause", "SELECT o_custkey, count(*) FILTER (o_orderstatus = 'F') AS done, round(coalesce(sum(o_totalprice) FILTER (o_orderstatus = 'O'), 0), 2) AS open_total FROM orders GROUP BY o_custkey")
def agg_filter_clause(spark, sf):
    return load(spark, sf, "orders").groupBy("o_custkey").agg(F.count_if(F.col("o_orderstatus") == "F").alias("done"), F.round(F.coalesce(F.sum(F.when(F.col("o_orderstatus") == "O", F.col("o_totalprice"))), F.lit(0.0)), 2).alias("open_total"))


_GROUPED = "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY {}"
query("agg_grouping_sets", _GROUPED.format("GROUPING SETS ((l_returnflag, l_linestatus), (l_linestatus), ())"))(
    lambda spark, sf: load(spark, sf, "lineitem").groupingSets([["l_returnflag", "l_linestatus"], ["l_linestatus"], []], "l_returnflag", "l_linestatus").agg(_n()))
query("agg_cube", _GROUPED.format("CUBE (l_returnflag, l_linestatus)"))(lambda spark, sf: load(spark, sf, "lineitem").cube("l_returnflag", "l_linestatus").agg(_n()))
query("agg_rollup", _GROUPED.format("ROLLUP (l_returnflag, l_linestatus)"))(lambda spark, sf: load(spark, sf, "lineitem").rollup("l_returnflag", "l_linestatus").agg(_n()))


@query("agg_pivot", "SELECT l_returnflag, count(*) FILTER (l_linestatus = 'F') AS \"F\", count(*) FILTER (l_linestatus = 'O') AS \"O\" FROM lineitem GROUP BY l_returnflag")
def agg_pivot(spark, sf):
    return load(spark, sf, "lineitem", ["l_returnflag", "l_linestatus"]).groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.count(F.lit(1))).na.fill(0)


# ---- windows --------------------------------------------------------------------------------------------------------

@query("win_rank", "SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, ntile(4) OVER w AS nt, round(percent_rank() OVER v, 9) AS pr FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey), v AS (PARTITION BY o_custkey ORDER BY o_orderstatus)")
def win_rank(spark, sf):
    w, v = Window.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey"), Window.partitionBy("o_custkey").orderBy("o_orderstatus")
    big = lambda c: c.cast("bigint")
    return load(spark, sf, "orders").select("o_orderkey", big(F.row_number().over(w)).alias("rn"), big(F.rank().over(v)).alias("rk"), big(F.dense_rank().over(v)).alias("dr"), big(F.ntile(4).over(w)).alias("nt"), F.round(F.percent_rank().over(v), 9).alias("pr"))


_W = "(PARTITION BY user_id ORDER BY ts, event_id)"


def _events(spark, sf):
    return load(spark, sf, "events", ["event_id", "user_id", "ts", "value"]), Window.partitionBy("user_id").orderBy("ts", "event_id")


@query("win_lag_lead", f"SELECT event_id, lag(value) OVER w AS before, lead(event_id, 2, -1) OVER w AS after FROM events WINDOW w AS {_W}")
def win_lag_lead(spark, sf):
    e, w = _events(spark, sf)
    return e.select("event_id", F.lag("value").over(w).alias("before"), F.lead("event_id", 2, -1).over(w).alias("after"))


@query("win_first_last", f"SELECT event_id, first_value(event_id) OVER w AS first_id, last_value(event_id) OVER w AS last_id, nth_value(event_id, 2) OVER w AS second_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def win_first_last(spark, sf):
    e, w = _events(spark, sf)
    w = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return e.select("event_id", F.first("event_id").over(w).alias("first_id"), F.last("event_id").over(w).alias("last_id"), F.nth_value("event_id", 2).over(w).alias("second_id"))


@query("win_running_rows", f"SELECT event_id, round(sum(value) OVER w, 6) AS running FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING)")
def win_running_rows(spark, sf):
    e, w = _events(spark, sf)
    return e.select("event_id", F.round(F.sum("value").over(w.rowsBetween(Window.unboundedPreceding, 0)), 6).alias("running"))


@query("win_sliding_rows", f"SELECT event_id, round(avg(value) OVER w, 6) AS moving FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING)")
def win_sliding_rows(spark, sf):
    e, w = _events(spark, sf)
    return e.select("event_id", F.round(F.avg("value").over(w.rowsBetween(-2, 2)), 6).alias("moving"))


@query("win_range_interval", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW) AS n FROM events")
def win_range_interval(spark, sf):
    e = as_timestamp(load(spark, sf, "events", ["event_id", "user_id", "ts"]), "ts")
    micros = F.unix_micros("ts")
    return e.select("event_id", F.count(F.lit(1)).over(Window.partitionBy("user_id").orderBy(micros).rangeBetween(-3_600_000_000, 0)).alias("n"))


# ---- sort, limit, top-k, sets ---------------------------------------------------------------------------------------

@query("sort_global", "SELECT o_orderkey, row_number() OVER (ORDER BY o_totalprice DESC, o_orderkey) - 1 AS place FROM orders")
def sort_global(spark, sf):
    return R.global_rank(load(spark, sf, "orders", ["o_orderkey", "o_totalprice"]), [F.desc("o_totalprice"), F.asc("o_orderkey")], "place").select("o_orderkey", "place")


@query("topk_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")
def topk_global(spark, sf):
    return load(spark, sf, "orders", ["o_orderkey", "o_totalprice"]).orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25)


@query("topk_per_group", "SELECT source, doc_id, n_chars FROM (SELECT *, row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id) AS rn FROM documents) WHERE rn <= 3")
def topk_per_group(spark, sf):
    return R.top_k(load(spark, sf, "documents", ["source", "doc_id", "n_chars"]), ["source"], [F.desc("n_chars"), F.asc("doc_id")], 3)


@query("limit_offset", "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 10 OFFSET 20")
def limit_offset(spark, sf):
    return load(spark, sf, "orders", ["o_orderkey"]).orderBy("o_orderkey").offset(20).limit(10)


def _sides(spark, sf):
    return load(spark, sf, "orders").select(F.col("o_custkey").alias("k")), load(spark, sf, "customer").select(F.col("c_custkey").alias("k"))


_A, _B = "SELECT o_custkey AS k FROM orders", "SELECT c_custkey AS k FROM customer"
for _name, _sql, _fn in (
    ("set_union", "UNION", lambda a, b: a.union(b).distinct()), ("set_union_all", "UNION ALL", lambda a, b: a.unionAll(b)),
    ("set_intersect", "INTERSECT", lambda a, b: a.intersect(b)), ("set_intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b)),
    ("set_except", "EXCEPT", lambda a, b: a.subtract(b)), ("set_except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b)),
):
    query(_name, f"({_A}) {_sql} ({_B})")(lambda spark, sf, fn=_fn: fn(*_sides(spark, sf)))


@query("set_distinct", "SELECT DISTINCT l_returnflag, l_linestatus FROM lineitem")
def set_distinct(spark, sf):
    return load(spark, sf, "lineitem", ["l_returnflag", "l_linestatus"]).distinct()


# ---- functions ------------------------------------------------------------------------------------------------------

@query("fn_string", "SELECT p_partkey, upper(p_name) AS up, substr(p_name, 2, 5) AS part, lpad(p_partkey::VARCHAR, 8, '0') AS padded, reverse(p_type) AS back, replace(p_type, ' ', '-') AS dashed, instr(p_name, 'a')::INT AS at_a, length(p_name)::INT AS size FROM part")
def fn_string(spark, sf):
    return load(spark, sf, "part").select("p_partkey", F.upper("p_name").alias("up"), F.substring("p_name", 2, 5).alias("part"), F.lpad(F.col("p_partkey").cast("string"), 8, "0").alias("padded"), F.reverse("p_type").alias("back"), F.replace("p_type", F.lit(" "), F.lit("-")).alias("dashed"), F.instr("p_name", "a").alias("at_a"), F.length("p_name").alias("size"))


@query("fn_regex", "SELECT doc_id, len(regexp_extract_all(text, '[A-Z][a-z]+'))::INT AS capitals, regexp_extract(text, '([a-z]+)[.]', 1) AS before_stop, length(regexp_replace(text, '[^a-z]', '', 'g'))::INT AS letters FROM documents")
def fn_regex(spark, sf):
    return load(spark, sf, "documents").select("doc_id", F.regexp_count("text", F.lit("[A-Z][a-z]+")).alias("capitals"), F.regexp_extract("text", "([a-z]+)[.]", 1).alias("before_stop"), F.length(F.regexp_replace("text", "[^a-z]", "")).alias("letters"))


@query("fn_hash", "SELECT doc_id, md5(text) AS m, sha256(text) AS s FROM documents")
def fn_hash(spark, sf):
    return load(spark, sf, "documents").select("doc_id", F.md5("text").alias("m"), F.sha2("text", 256).alias("s"))


@query("fn_levenshtein", "SELECT a.n_name AS a, b.n_name AS b, levenshtein(a.n_name, b.n_name)::INT AS d FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
def fn_levenshtein(spark, sf):
    return QUERIES["join_theta_size"](spark, sf).withColumn("d", F.levenshtein("a", "b"))


@query("fn_split_explode", "SELECT word, count(*) AS n FROM (SELECT unnest(string_split(text, ' ')) AS word FROM documents) GROUP BY word HAVING count(*) >= 50")
def fn_split_explode(spark, sf):
    return load(spark, sf, "documents").select(F.explode(F.split("text", " ")).alias("word")).groupBy("word").agg(_n()).filter("n >= 50")


@query("fn_date_trunc", "SELECT date_trunc('month', o_orderdate)::TIMESTAMP AS month, count(*) AS n FROM orders GROUP BY 1")
def fn_date_trunc(spark, sf):
    return load(spark, sf, "orders").groupBy(F.date_trunc("month", "o_orderdate").cast("timestamp_ntz").alias("month")).agg(_n())


@query("fn_date_arith", "SELECT o_orderkey, (o_orderdate + INTERVAL 90 DAY)::DATE AS due, datediff('day', DATE '1992-01-01', o_orderdate::DATE)::INT AS days, last_day(o_orderdate::DATE) AS month_end FROM orders")
def fn_date_arith(spark, sf):
    d = F.col("o_orderdate").cast("date")
    return load(spark, sf, "orders").select("o_orderkey", F.date_add(d, 90).alias("due"), F.datediff(d, F.lit("1992-01-01").cast("date")).alias("days"), F.last_day(d).alias("month_end"))


@query("fn_extract", "SELECT o_orderkey, year(o_orderdate)::INT AS y, quarter(o_orderdate)::INT AS q, isodow(o_orderdate)::INT AS d, week(o_orderdate)::INT AS w FROM orders")
def fn_extract(spark, sf):
    return load(spark, sf, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.quarter("o_orderdate").alias("q"), (F.weekday("o_orderdate") + 1).alias("d"), F.weekofyear("o_orderdate").alias("w"))


@query("fn_math", "SELECT p_partkey, round(ln(p_retailprice), 9) AS l, round(exp(p_size / 50.0), 9) AS e, round(sqrt(p_retailprice), 9) AS s, round(pow(p_size, 1.5), 9) AS w, sign(p_retailprice - 1200)::INT AS g, p_partkey % 7 AS m FROM part")
def fn_math(spark, sf):
    return load(spark, sf, "part").select("p_partkey", F.round(F.log("p_retailprice"), 9).alias("l"), F.round(F.exp(F.col("p_size") / 50.0), 9).alias("e"), F.round(F.sqrt("p_retailprice"), 9).alias("s"), F.round(F.pow("p_size", F.lit(1.5)), 9).alias("w"), F.signum(F.col("p_retailprice") - 1200).cast("int").alias("g"), (F.col("p_partkey") % 7).alias("m"))


@query("fn_decimal", "SELECT l_returnflag, sum(l_extendedprice::DECIMAL(12,2))::DECIMAL(22,2) AS total FROM lineitem GROUP BY l_returnflag")
def fn_decimal(spark, sf):
    return load(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.sum(F.col("l_extendedprice").cast("decimal(12,2)")).cast("decimal(22,2)").alias("total"))


@query("fn_width_bucket", "SELECT least(11, greatest(0, floor(l_quantity / 5) + 1))::BIGINT AS b, count(*) AS n FROM lineitem GROUP BY 1")
def fn_width_bucket(spark, sf):
    return load(spark, sf, "lineitem").groupBy(F.width_bucket("l_quantity", F.lit(0.0), F.lit(50.0), F.lit(10)).alias("b")).agg(_n())


@query("fn_try", "SELECT o_orderkey, try_cast(o_orderpriority[1:1] AS INT) AS level, CASE WHEN o_custkey % 5 = 0 THEN NULL ELSE o_totalprice / (o_custkey % 5) END AS ratio FROM orders")
def fn_try(spark, sf):
    return load(spark, sf, "orders").select("o_orderkey", F.substring("o_orderpriority", 1, 1).try_cast("int").alias("level"), F.try_divide("o_totalprice", F.col("o_custkey") % 5).alias("ratio"))


_WORDS = "list_distinct(regexp_extract_all(lower(text), '[a-z]+'))"


@query("fn_array_sets", f"SELECT doc_id, len(list_intersect(w, ['the', 'of', 'de', 'la']))::INT AS common, len(list_filter(w, lambda x: NOT list_contains(['the', 'of'], x)))::INT AS others, list_contains(w, 'the') AS has_the FROM (SELECT doc_id, {_WORDS} AS w FROM documents)")
def fn_array_sets(spark, sf):
    w = load(spark, sf, "documents").select("doc_id", F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0))).alias("w"))
    lits = lambda *x: F.array(*[F.lit(v) for v in x])
    return w.select("doc_id", F.size(F.array_intersect("w", lits("the", "of", "de", "la"))).alias("common"), F.size(F.array_except("w", lits("the", "of"))).alias("others"), F.array_contains("w", "the").alias("has_the"))


@query("fn_array_hof", f"SELECT doc_id, list_sum(list_transform(w, lambda x: length(x)))::BIGINT AS letters, len(list_filter(w, lambda x: length(x) > 6))::INT AS long_words FROM (SELECT doc_id, {_WORDS} AS w FROM documents) WHERE len(w) > 0")
def fn_array_hof(spark, sf):
    w = load(spark, sf, "documents").select("doc_id", F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0))).alias("w")).filter(F.size("w") > 0)
    return w.select("doc_id", F.aggregate("w", F.lit(0).cast("bigint"), lambda s, x: s + F.length(x)).alias("letters"), F.size(F.filter("w", lambda x: F.length(x) > 6)).alias("long_words"))


@query("fn_map", "SELECT lang, count(*) AS n, count(*) FILTER (n_chars > 1000) AS long_docs FROM documents GROUP BY lang")
def fn_map(spark, sf):
    docs = load(spark, sf, "documents").select("lang", F.create_map(F.lit("n"), F.lit(1), F.lit("long"), (F.col("n_chars") > 1000).cast("int")).alias("m"))
    return docs.groupBy("lang").agg(F.sum(F.col("m")["n"]).alias("n"), F.sum(F.col("m")["long"]).alias("long_docs"))


@query("fn_json", "SELECT event_id, json_extract_string(props, '$.k') AS k, length(props)::INT AS size FROM events")
def fn_json(spark, sf):
    return load(spark, sf, "events").select("event_id", F.get_json_object("props", "$.k").alias("k"), F.length("props").alias("size"))


@query("sample_hash", "SELECT doc_id FROM documents WHERE ('0x' || substr(md5('s' || doc_id), 1, 4))::INT % 10 = 0")
def sample_hash(spark, sf):
    return R.hash_sample(load(spark, sf, "documents", ["doc_id"]), "doc_id", "s", 10)


@query("sample_stratified")
def sample_stratified(spark, sf):
    return load(spark, sf, "documents").sampleBy("lang", {"en": 0.1, "de": 0.3, "fr": 0.3, "es": 0.3}, 7).groupBy("lang").agg(_n())


# ---- UDF surface ----------------------------------------------------------------------------------------------------

@query("udf_scalar_pandas", "SELECT doc_id, length(text)::BIGINT AS size FROM documents")
def udf_scalar_pandas(spark, sf):
    size = F.pandas_udf(lambda s: s.str.len(), T.LongType(), F.PandasUDFType.SCALAR)
    return load(spark, sf, "documents").select("doc_id", size("text").alias("size"))


@query("udf_iter_pandas", "SELECT doc_id, len(regexp_extract_all(text, '[a-z]+'))::BIGINT AS n FROM documents WHERE text IS NOT NULL")
def udf_iter_pandas(spark, sf):
    """Iterator form: the pattern is compiled once for each task, not for each batch."""
    def count(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        word = re.compile("[a-z]+")
        for texts in batches:
            yield texts.map(lambda t: len(word.findall(t))).astype("int64")

    counted = F.pandas_udf(count, T.LongType())
    return load(spark, sf, "documents", ["doc_id", "text"]).filter("text IS NOT NULL").select("doc_id", counted("text").alias("n"))


@query("udaf_grouped_agg", "SELECT o_custkey, round(max(o_totalprice) - min(o_totalprice), 6) AS spread FROM orders GROUP BY o_custkey")
def udaf_grouped_agg(spark, sf):
    def spread(values: pd.Series) -> float:
        return float(values.max() - values.min())

    wide = F.pandas_udf(spread, T.DoubleType())
    return load(spark, sf, "orders", ["o_custkey", "o_totalprice"]).groupBy("o_custkey").agg(wide("o_totalprice").alias("spread")).select("o_custkey", F.round("spread", 6).alias("spread"))


@query("udf_map_in_arrow", "SELECT doc_id, n_chars * 2 AS twice FROM documents")
def udf_map_in_arrow(spark, sf):
    import pyarrow as pa
    import pyarrow.compute as pc

    def run(batches):
        for b in batches:
            yield pa.record_batch([b.column(0), pc.multiply(b.column(1), 2)], names=["doc_id", "twice"])

    return load(spark, sf, "documents", ["doc_id", "n_chars"]).mapInArrow(run, "doc_id bigint, twice bigint")


@query("udf_grouped_map", "SELECT o_custkey, o_orderkey, o_totalprice - max(o_totalprice) OVER (PARTITION BY o_custkey) AS gap FROM orders")
def udf_grouped_map(spark, sf):
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"o_custkey": pdf["o_custkey"], "o_orderkey": pdf["o_orderkey"], "gap": pdf["o_totalprice"] - pdf["o_totalprice"].max()})

    return load(spark, sf, "orders", ["o_custkey", "o_orderkey", "o_totalprice"]).groupBy("o_custkey").applyInPandas(run, "o_custkey bigint, o_orderkey bigint, gap double")


@query("udtf_functions", "SELECT doc_id, count(*) AS n FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE line <> '' GROUP BY doc_id")
def udtf_functions(spark, sf):
    from paircuration import udfs

    udfs.register(spark)
    return tables.run_sql(spark, "SELECT doc_id, count(*) AS n FROM @docs@, LATERAL lines_of(text) GROUP BY doc_id", docs=load(spark, sf, "documents", ["doc_id", "text"]))


@query("udf_sql_names", "SELECT conv_id, turn, len(list_intersect(a, b)) / len(list_distinct(list_concat(a, b))) AS similarity FROM (SELECT x.conv_id, x.turn, list_distinct(regexp_extract_all(lower(x.text), '[a-z0-9_]+')) AS a, list_distinct(regexp_extract_all(lower(y.text), '[a-z0-9_]+')) AS b FROM conversations x JOIN conversations y ON x.conv_id = y.conv_id AND x.turn = y.turn + 1) WHERE len(a) + len(b) > 0")
def udf_sql_names(spark, sf):
    from paircuration import udfs

    udfs.register(spark)
    c = load(spark, sf, "conversations")
    return tables.run_sql(spark, "SELECT x.conv_id, x.turn, token_jaccard(x.text, y.text) AS similarity FROM @c@ x JOIN @c@ y ON x.conv_id = y.conv_id AND x.turn = y.turn + 1 WHERE regexp_count(lower(concat(x.text, y.text)), '[a-z0-9_]') > 0", c=c)
