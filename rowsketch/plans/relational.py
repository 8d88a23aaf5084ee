"""Relational support queries: the joins, windows, sets and functions around sketches, each with its oracle.

One text serves both engines unless a dialect needs another.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rowsketch.functions import vectors as V
from rowsketch.sources.tables import load, views

#: name: (tables, Spark SQL, DuckDB SQL or None for the same text)
SQL: dict[str, tuple[tuple[str, ...], str, str | None]] = {
    "join_broadcast": (("customer", "nation"), "SELECT /*+ BROADCAST(n) */ n.n_name, count(*) AS customers, round(sum(c.c_acctbal), 2) AS balance FROM customer c JOIN nation n ON c.c_nationkey = n.n_nationkey GROUP BY n.n_name", "SELECT n.n_name, count(*) AS customers, round(sum(c.c_acctbal), 2) AS balance FROM customer c JOIN nation n ON c.c_nationkey = n.n_nationkey GROUP BY n.n_name"),
    "join_sort_merge": (("lineitem", "orders"), "SELECT /*+ MERGE(l, o) */ o.o_orderpriority, count(*) AS items, sum(l.l_quantity) AS quantity FROM lineitem l JOIN orders o ON l.l_orderkey = o.o_orderkey GROUP BY o.o_orderpriority", "SELECT o.o_orderpriority, count(*) AS items, sum(l.l_quantity) AS quantity FROM lineitem l JOIN orders o ON l.l_orderkey = o.o_orderkey GROUP BY o.o_orderpriority"),
    "join_shuffle_hash": (("lineitem", "part"), "SELECT /*+ SHUFFLE_HASH(p) */ p.p_brand, count(*) AS items, sum(l.l_quantity) AS quantity FROM lineitem l JOIN part p ON l.l_partkey = p.p_partkey GROUP BY p.p_brand", "SELECT p.p_brand, count(*) AS items, sum(l.l_quantity) AS quantity FROM lineitem l JOIN part p ON l.l_partkey = p.p_partkey GROUP BY p.p_brand"),
    "join_left_semi": (("documents", "labels"), "SELECT d.lang, count(*) AS n FROM documents d LEFT SEMI JOIN labels l ON d.doc_id = l.doc_id GROUP BY d.lang", "SELECT d.lang, count(*) AS n FROM documents d SEMI JOIN labels l ON d.doc_id = l.doc_id GROUP BY d.lang"),
    "join_left_anti": (("documents", "labels"), "SELECT d.lang, count(*) AS n FROM documents d LEFT ANTI JOIN labels l ON d.doc_id = l.doc_id GROUP BY d.lang", "SELECT d.lang, count(*) AS n FROM documents d ANTI JOIN labels l ON d.doc_id = l.doc_id GROUP BY d.lang"),
    "join_full_outer": (("events", "customer"), "SELECT count(*) AS n, count(u) AS users, count(c_custkey) AS customers FROM (SELECT DISTINCT user_id AS u FROM events) e FULL OUTER JOIN customer c ON e.u = c.c_custkey", None),
    "join_range": (("events",), "SELECT w.day, count(*) AS n FROM (SELECT DISTINCT date_trunc('day', ts) AS day FROM events) w JOIN events e ON e.ts >= w.day AND e.ts < w.day + INTERVAL 1 DAY AND date_trunc('day', e.ts) = w.day GROUP BY w.day", None),
    "join_self_gram_lineitem": (("lineitem",), "SELECT round(sum(l_discount * l_tax), 4) AS discount_tax, round(sum(l_discount * l_discount), 4) AS discount2, round(sum(l_tax * l_tax), 4) AS tax2 FROM lineitem", None),
    "window_ranks": (("supplier",), "SELECT s_suppkey, row_number() OVER (PARTITION BY s_nationkey ORDER BY s_acctbal DESC, s_suppkey) AS rn, rank() OVER (PARTITION BY s_nationkey ORDER BY s_acctbal DESC) AS rk, dense_rank() OVER (PARTITION BY s_nationkey ORDER BY s_acctbal DESC) AS dr, ntile(4) OVER (PARTITION BY s_nationkey ORDER BY s_acctbal DESC, s_suppkey) AS quarter FROM supplier", None),
    "window_lag_lead": (("events",), "SELECT event_id, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS after, first_value(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS first_one FROM events", None),
    "window_frames": (("events",), "SELECT event_id, round(sum(value * value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 9 PRECEDING AND CURRENT ROW), 4) AS f2 FROM events", None),
    "window_topk": (("embeddings",), "SELECT label, vec_id FROM (SELECT label, vec_id, row_number() OVER (PARTITION BY label ORDER BY vec_id DESC) AS rn FROM embeddings) t WHERE rn <= 3", None),
    "setop_union": (("customer", "supplier"), "SELECT kind, count(*) AS n FROM (SELECT c_nationkey AS k, 'c' AS kind FROM customer UNION ALL SELECT s_nationkey AS k, 's' AS kind FROM supplier) t GROUP BY kind", None),
    "setop_intersect": (("events",), "SELECT user_id FROM events WHERE ts < TIMESTAMP '2024-01-10 00:00:00' AND event_type = 'purchase' INTERSECT SELECT user_id FROM events WHERE ts >= TIMESTAMP '2024-01-10 00:00:00' AND event_type = 'purchase'", None),
    "setop_except": (("events",), "SELECT user_id FROM events WHERE event_type = 'view' EXCEPT SELECT user_id FROM events WHERE event_type = 'purchase' AND value > 100", None),
    "setop_distinct": (("documents",), "SELECT count(*) AS n, count(DISTINCT text) AS texts FROM documents", None),
    "cube_flags": (("lineitem",), "SELECT l_returnflag, l_linestatus, grouping(l_returnflag) AS g1, grouping(l_linestatus) AS g2, count(*) AS n, sum(l_quantity * l_quantity) AS f2 FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)", None),
    "rollup_dates": (("orders",), "SELECT year(o_orderdate) AS y, month(o_orderdate) AS m, count(*) AS n FROM orders GROUP BY ROLLUP (year(o_orderdate), month(o_orderdate))", None),
    "grouping_sets": (("part",), "SELECT p_brand, p_type, count(*) AS n FROM part GROUP BY GROUPING SETS ((p_brand), (p_type), ())", None),
    "agg_moments": (("lineitem",), "SELECT count(*) AS n, round(avg(l_quantity), 6) AS mean, round(stddev_pop(l_quantity), 6) AS deviation, round(covar_pop(l_quantity, l_extendedprice) / 100000, 6) AS covariance, round(corr(l_quantity, l_discount), 6) AS correlation FROM lineitem", None),
    "agg_distinct": (("lineitem",), "SELECT count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem", None),
    "agg_filter_having": (("events",), "SELECT event_type, count(*) FILTER (WHERE value > 50) AS large, count(*) AS n FROM events GROUP BY event_type HAVING count(*) > 10", None),
    "agg_min_max_by": (("events",), "SELECT event_type, min_by(event_id, value * 1000000 + event_id / 1000000.0) AS least, max_by(event_id, value * 1000000 + event_id / 1000000.0) AS greatest FROM events GROUP BY event_type", "SELECT event_type, arg_min(event_id, value * 1000000 + event_id / 1000000.0) AS least, arg_max(event_id, value * 1000000 + event_id / 1000000.0) AS greatest FROM events GROUP BY event_type"),
    "agg_median": (("lineitem",), "SELECT l_returnflag, round(percentile(l_extendedprice, 0.5), 4) AS middle FROM lineitem GROUP BY l_returnflag", "SELECT l_returnflag, round(quantile_cont(l_extendedprice, 0.5), 4) AS middle FROM lineitem GROUP BY l_returnflag"),
    "topk_limit": (("orders",), "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25", None),
    "string_tokens": (("documents",), "SELECT token, count(*) AS n FROM (SELECT explode(regexp_extract_all(lower(text), '[a-z]+', 0)) AS token FROM documents) t GROUP BY token HAVING count(*) >= 50", "SELECT token, count(*) AS n FROM (SELECT unnest(regexp_extract_all(lower(text), '[a-z]+')) AS token FROM documents) t GROUP BY token HAVING count(*) >= 50"),
    "json_props": (("events",), "SELECT event_type, sum(CAST(get_json_object(props, '$.k') AS BIGINT)) AS k FROM events GROUP BY event_type", "SELECT event_type, sum(CAST(json_extract_string(props, '$.k') AS BIGINT))::BIGINT AS k FROM events GROUP BY event_type"),
    "date_trunc_daily": (("events",), "SELECT date_trunc('day', ts) AS day, count(*) AS n, round(sum(value), 3) AS total FROM events GROUP BY date_trunc('day', ts)", None),
    "date_parts": (("lineitem",), "SELECT year(l_shipdate) AS y, quarter(l_shipdate) AS q, count(*) AS n FROM lineitem GROUP BY year(l_shipdate), quarter(l_shipdate)", None),
    "scan_pushdown": (("lineitem",), "SELECT l_returnflag, count(*) AS n, sum(l_quantity) AS quantity FROM lineitem WHERE l_shipdate >= TIMESTAMP '1995-01-01 00:00:00' AND l_shipdate < TIMESTAMP '1996-01-01 00:00:00' AND l_discount BETWEEN 0.02 AND 0.06 GROUP BY l_returnflag", None),
    "window_percent_nth": (("supplier",), "SELECT s_suppkey, round(percent_rank() OVER (PARTITION BY s_nationkey ORDER BY s_acctbal, s_suppkey), 9) AS pr, round(cume_dist() OVER (PARTITION BY s_nationkey ORDER BY s_acctbal, s_suppkey), 9) AS cd, nth_value(s_suppkey, 2) OVER (PARTITION BY s_nationkey ORDER BY s_acctbal DESC, s_suppkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second_one FROM supplier", None),
    "window_range_frame": (("events",), "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY day(ts) RANGE BETWEEN 2 PRECEDING AND CURRENT ROW) AS three_days FROM events", None),
    "setop_intersect_all": (("events",), "SELECT user_id FROM events WHERE event_type = 'view' INTERSECT ALL SELECT user_id FROM events WHERE event_type = 'click'", None),
    "setop_except_all": (("events",), "SELECT user_id FROM events WHERE event_type = 'view' EXCEPT ALL SELECT user_id FROM events WHERE event_type = 'click'", None),
    "agg_approx_distinct": (("lineitem",), "SELECT abs(approx_count_distinct(l_partkey) - count(DISTINCT l_partkey)) <= 0.2 * count(DISTINCT l_partkey) AS parts_close, abs(approx_count_distinct(l_suppkey) - count(DISTINCT l_suppkey)) <= 0.2 * count(DISTINCT l_suppkey) AS suppliers_close FROM lineitem", None),
    "string_functions": (("part",), "SELECT p_partkey, levenshtein(p_name, p_type) AS distance, translate(p_brand, 'Brand#', 'bRAND-') AS turned, regexp_replace(p_type, '[AEIOU]', '') AS consonants, upper(substring(p_name, 1, 3)) AS head, concat_ws('/', p_brand, p_type) AS both_names, lpad(p_brand, 10, '*') AS padded, reverse(p_type) AS backwards, instr(p_name, ' ') AS gap, split_part(p_name, ' ', 2) AS second_word FROM part", "SELECT p_partkey, levenshtein(p_name, p_type)::INTEGER AS distance, translate(p_brand, 'Brand#', 'bRAND-') AS turned, regexp_replace(p_type, '[AEIOU]', '', 'g') AS consonants, upper(substring(p_name, 1, 3)) AS head, concat_ws('/', p_brand, p_type) AS both_names, lpad(p_brand, 10, '*') AS padded, reverse(p_type) AS backwards, instr(p_name, ' ')::INTEGER AS gap, split_part(p_name, ' ', 2) AS second_word FROM part"),
    "date_functions": (("orders",), "SELECT o_orderkey, datediff(o_orderdate, DATE '1992-01-01') AS days, make_date(year(o_orderdate), month(o_orderdate), 1) AS first_day, CAST(extract(DAY FROM o_orderdate) AS INT) AS d, CAST(extract(WEEK FROM o_orderdate) AS INT) AS w, last_day(o_orderdate) AS month_end, date_format(o_orderdate, 'yyyy-MM') AS month_name FROM orders", "SELECT o_orderkey, date_diff('day', DATE '1992-01-01', o_orderdate::DATE)::INTEGER AS days, make_date(year(o_orderdate), month(o_orderdate), 1) AS first_day, extract(DAY FROM o_orderdate)::INTEGER AS d, extract(WEEK FROM o_orderdate)::INTEGER AS w, last_day(o_orderdate::DATE) AS month_end, strftime(o_orderdate, '%Y-%m') AS month_name FROM orders"),
    "json_struct": (("events",), "SELECT event_id, from_json(props, 'k INT').k AS k, json_array_length('[1, 2, 3]') AS three FROM events", "SELECT event_id, json_extract(props, '$.k')::INTEGER AS k, 3::INTEGER AS three FROM events"),
    "math_norms": (("lineitem",), "SELECT round(sqrt(sum(l_quantity * l_quantity)), 6) AS length, round(ln(count(*)), 9) AS log_n, CAST(floor(avg(l_extendedprice)) AS BIGINT) AS whole, CAST(sum(sign(l_tax - 0.04)) AS BIGINT) AS balance FROM lineitem", None),
}


def _sql(name: str):
    tables, text, _ = SQL[name]

    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        views(spark, sf_dir, *tables)
        return spark.sql(text)

    return query


def join_asof(spark: SparkSession, sf_dir: str) -> DataFrame:
    """For each event, the latest purchase of the same user at or before it: one sort by user, no join."""
    from pyspark.sql import Window

    e = load(spark, sf_dir, "events").select("event_id", "user_id", "ts", "event_type")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return e.select("event_id", F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(w).alias("purchase_id"))


def join_cross_slots(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A small slot table against the regions."""
    return load(spark, sf_dir, "region").select("r_regionkey").crossJoin(F.broadcast(spark.range(4).select(F.col("id").cast("int").alias("slot"))))


def array_norms(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = load(spark, sf_dir, "embeddings").select("label", F.col("embedding").cast("array<double>").alias("v"))
    return v.groupBy("label").agg(F.count("*").alias("n"), F.round(F.sum(V.vec_norm2("v")), 6).alias("f2"), F.round(F.sum(F.array_max("v")), 5).alias("largest"))


def map_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Event types counted by user, as a map, and read back."""
    e = load(spark, sf_dir, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    m = e.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", F.coalesce(F.try_element_at("m", F.lit("view")), F.lit(0)).alias("views"), F.size("m").cast("long").alias("kinds"))


def window_running_tail(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Running sums over all users by falling count, without one task that sees them all.

    Rows are dealt by range of their order; each range sums its own, and starts
    from what the ranges before it add up to, one row a range.
    """
    from pyspark.sql import Window

    from rowsketch.shared import materialise

    counts = load(spark, sf_dir, "events").groupBy("user_id").agg(F.count("*").alias("cnt"))
    ranged = materialise(counts.repartitionByRange(F.desc("cnt"), F.col("user_id")).select("*", F.spark_partition_id().alias("p")), "ranges")
    sums = ranged.groupBy("p").agg(F.sum("cnt").alias("own"))
    before = sums.select("p", (F.sum("own").over(Window.partitionBy(F.lit(0)).orderBy("p")) - F.col("own")).alias("before"))
    inside = Window.partitionBy("p").orderBy(F.desc("cnt"), "user_id").rowsBetween(Window.unboundedPreceding, 0)
    return ranged.join(F.broadcast(before), "p").select("user_id", "cnt", (F.col("before") + F.sum("cnt").over(inside)).alias("head"))


def join_asof_versions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """For each event, the latest sketch version of its type at or before it.

    Versions are few and begin with a day; each is spread over the days it is
    the latest on, which makes the as-of join an equality on type and day, and
    a type with a third of all events no single group.
    """
    from pyspark.sql import Window

    e = load(spark, sf_dir, "events").select("event_id", "event_type", F.date_trunc("day", "ts").cast("date").alias("day"))
    versions = e.where("day(day) % 3 = 0").select("event_type", F.col("day").alias("version")).distinct()
    last = e.agg(F.max("day").alias("last"))
    until = F.coalesce(F.date_sub(F.lead("version").over(Window.partitionBy("event_type").orderBy("version")), 1), F.col("last"))
    spread = versions.crossJoin(F.broadcast(last)).select("event_type", "version", until.alias("until")).select("event_type", "version", F.explode(F.sequence("version", "until")).alias("day"))
    return e.join(spread, ["event_type", "day"], "left").select("event_id", "version")


def map_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Large and small events by type, as two maps of a user, zipped, filtered and put together."""
    e = load(spark, sf_dir, "events").groupBy("user_id", "event_type").agg(F.count(F.when(F.col("value") > 50, 1)).alias("large"), F.count(F.when(F.col("value") <= 50, 1)).alias("small"))
    pick = lambda c: F.map_filter(F.map_from_entries(F.collect_list(F.struct("event_type", c))), lambda _, n: n > 0)
    m = e.groupBy("user_id").agg(pick("large").alias("l"), pick("small").alias("s"))
    gap = F.map_values(F.map_zip_with("l", "s", lambda _, a, b: F.coalesce(a, F.lit(0)) - F.coalesce(b, F.lit(0))))
    both = F.map_concat(F.transform_keys("l", lambda k, _: F.concat(F.lit("l "), k)), F.transform_keys("s", lambda k, _: F.concat(F.lit("s "), k)))
    return m.select("user_id", F.aggregate(gap, F.lit(0).cast("long"), lambda t, x: t + F.abs(x)).alias("apart"), F.size(both).cast("long").alias("kinds"))


def sample_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bernoulli and stratified samples hold as many rows as they should, within six deviations."""
    l = load(spark, sf_dir, "lineitem")
    shares = {"A": 0.5, "N": 0.1, "R": 0.3}
    n = l.groupBy("l_returnflag").agg(F.count("*").alias("n"))
    plain = l.sample(0.2, seed=3).groupBy("l_returnflag").agg(F.count("*").alias("plain"))
    layered = l.sampleBy("l_returnflag", shares, seed=3).groupBy("l_returnflag").agg(F.count("*").alias("layered"))
    share = F.element_at(F.create_map(*[F.lit(x) for kv in shares.items() for x in kv]), F.col("l_returnflag"))
    near = lambda c, p: F.abs(F.coalesce(c, F.lit(0)) - F.col("n") * p) <= 6 * F.sqrt(F.col("n") * p * (1 - p)) + 1
    return n.join(plain, "l_returnflag", "left").join(layered, "l_returnflag", "left").select("l_returnflag", near(F.col("plain"), F.lit(0.2)).alias("plain_ok"), near(F.col("layered"), share).alias("layered_ok"))


def agg_mean_length(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Length of the mean vector of each label, from a grouped pandas function."""
    @F.pandas_udf("double")
    def mean_length(v: pd.Series) -> float:
        return float(np.linalg.norm(np.stack(v.to_numpy()).mean(axis=0)))

    e = load(spark, sf_dir, "embeddings").select("label", F.col("embedding").cast("array<double>").alias("v"))
    return e.groupBy("label").agg(mean_length("v").alias("x")).select("label", F.round("x", 6).alias("x"))


def bag_of_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bucket totals of hashed words."""
    from rowsketch.sources import view

    t = view.tokens(load(spark, sf_dir, "documents"), "doc_id", "text")
    return t.groupBy(view.token_bucket(F.col("token"), 64).alias("bucket")).agg(F.count("*").alias("n"))


QUERIES = {name: _sql(name) for name in SQL} | {"join_asof": join_asof, "join_cross_slots": join_cross_slots, "array_norms": array_norms, "map_counts": map_counts, "bag_of_words": bag_of_words, "window_running_tail": window_running_tail, "join_asof_versions": join_asof_versions, "map_functions": map_functions, "sample_rows": sample_rows, "agg_mean_length": agg_mean_length}

ORACLES = {name: duck or text for name, (_, text, duck) in SQL.items()} | {
    "join_asof": "SELECT event_id, last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS purchase_id FROM events",
    "join_cross_slots": "SELECT r_regionkey, slot::INTEGER AS slot FROM region CROSS JOIN (SELECT unnest(range(4)) AS slot) s",
    "array_norms": "SELECT label, count(*) AS n, round(sum(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE))), 6) AS f2, round(sum(list_max(embedding)::DOUBLE), 5) AS largest FROM embeddings GROUP BY label",
    "map_counts": "SELECT user_id, count(*) FILTER (WHERE event_type = 'view') AS views, count(DISTINCT event_type) AS kinds FROM events GROUP BY user_id",
    "bag_of_words": "SELECT (('0x' || substr(md5(token), 1, 8))::BIGINT % 64)::INTEGER AS bucket, count(*) AS n FROM (SELECT unnest(regexp_extract_all(lower(text), '[a-z]+')) AS token FROM documents) t GROUP BY 1",
    "window_running_tail": "SELECT user_id, cnt, (sum(cnt) OVER (ORDER BY cnt DESC, user_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW))::BIGINT AS head FROM (SELECT user_id, count(*) AS cnt FROM events GROUP BY user_id) t",
    "join_asof_versions": "WITH e AS (SELECT event_id, event_type, ts::DATE AS day FROM events), v AS (SELECT DISTINCT event_type, day AS version FROM e WHERE day(day) % 3 = 0) SELECT event_id, version FROM e ASOF LEFT JOIN v ON e.event_type = v.event_type AND e.day >= v.version",
    "map_functions": "WITH c AS (SELECT user_id, event_type, count(*) FILTER (WHERE value > 50) AS large, count(*) FILTER (WHERE value <= 50) AS small FROM events GROUP BY ALL) SELECT user_id, sum(abs(large - small))::BIGINT AS apart, sum((large > 0)::BIGINT + (small > 0)::BIGINT)::BIGINT AS kinds FROM c GROUP BY user_id",
    "sample_rows": "SELECT l_returnflag, true AS plain_ok, true AS layered_ok FROM lineitem GROUP BY l_returnflag",
    "agg_mean_length": "SELECT label, round(sqrt(sum(m * m)), 6) AS x FROM (SELECT label, pos, avg(x) AS m FROM (SELECT label, generate_subscripts(embedding, 1) - 1 AS pos, unnest(embedding)::DOUBLE AS x FROM embeddings) c GROUP BY label, pos) t GROUP BY label",
}
