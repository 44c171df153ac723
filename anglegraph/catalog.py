"""Relational operators around the graphs: one query for each, as one statement for Spark and SQL engines or as a DataFrame with its SQL."""

from __future__ import annotations

import re

from pyspark.sql import Window
from pyspark.sql import functions as F

from .functions.geometry import portable_hash
from .operators import neighbors as N
from .sources import vectors as V

STATEMENTS = {
    "op_scan_vectors": "SELECT vec_id, label FROM embeddings",
    "op_filter_range": "SELECT l_orderkey, l_linenumber, l_partkey FROM lineitem WHERE l_quantity BETWEEN 10 AND 12 AND l_returnflag IN ('A', 'R')",
    "op_filter_like_null": "SELECT p_partkey FROM part WHERE p_name LIKE '%a%' AND p_type IS NOT NULL",
    "op_split_99_1": "SELECT vec_id, vec_id % 100 = 37 AS valid FROM embeddings",
    "op_join_equi": "SELECT o_orderkey, c_name FROM orders JOIN customer ON o_custkey = c_custkey",
    "op_join_broadcast": "SELECT s_suppkey, n_name, r_name FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey",
    "op_join_semi": "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)",
    "op_join_anti": "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)",
    "op_join_full": "SELECT coalesce(a.c_nationkey, b.s_nationkey) AS nation, a.n AS customers, b.n AS suppliers FROM (SELECT c_nationkey, count(*) AS n FROM customer GROUP BY c_nationkey) a FULL JOIN (SELECT s_nationkey, count(*) AS n FROM supplier GROUP BY s_nationkey) b ON a.c_nationkey = b.s_nationkey",
    "op_join_interval": "SELECT a.event_id AS first, b.event_id AS second FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 5 MINUTE",
    "op_join_asof": "SELECT event_id, max(CASE WHEN event_type = 'purchase' THEN event_id END) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last_purchase FROM events",
    "op_agg_distinct": "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(*) AS n FROM lineitem GROUP BY l_returnflag",
    "op_agg_rollup": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)",
    "op_agg_cube": "SELECT event_type, user_id % 3 AS g, count(*) AS n FROM events GROUP BY CUBE (event_type, user_id % 3)",
    "op_agg_sets": "SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())",
    "op_agg_moments": "SELECT label, count(*) AS n FROM embeddings GROUP BY label HAVING count(*) > 45",
    "op_win_topk": "SELECT o_custkey, o_orderkey, r FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) t WHERE r <= 2",
    "op_win_ranks": "SELECT s_suppkey, rank() OVER (ORDER BY s_nationkey) AS rk, dense_rank() OVER (ORDER BY s_nationkey) AS dr, ntile(4) OVER (ORDER BY s_suppkey) AS nt FROM supplier",
    "op_win_lag": "SELECT event_id, lag(event_id) OVER (PARTITION BY user_id ORDER BY event_id) AS before, lead(event_id) OVER (PARTITION BY user_id ORDER BY event_id) AS after FROM events",
    "op_win_frames": "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS n FROM events",
    "op_win_running": "SELECT l_orderkey, l_partkey, l_suppkey, l_linenumber, count(*) OVER (PARTITION BY l_suppkey ORDER BY l_orderkey, l_linenumber, l_partkey) AS n FROM lineitem",
    "op_topn": "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25",
    "op_limit_offset": "SELECT c_custkey FROM customer ORDER BY c_custkey LIMIT 10 OFFSET 5",
    "op_union_distinct": "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier",
    "op_intersect": "SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier",
    "op_except": "SELECT n_nationkey AS k FROM nation EXCEPT SELECT s_nationkey FROM supplier WHERE s_suppkey < 5",
    "op_case_string": "SELECT n_nationkey, upper(n_name) AS u, length(n_name) AS n, replace(n_name, 'A', '_') AS r FROM nation",
    "op_math": "SELECT l_orderkey, l_linenumber, l_partkey, round(sqrt(l_quantity), 6) AS s, greatest(l_tax, l_discount) AS g FROM lineitem",
    "op_recursive": "WITH RECURSIVE t(n, top) AS (SELECT 1, CAST(max(l_quantity) AS INT) FROM lineitem UNION ALL SELECT n + 1, top FROM t WHERE n < top) SELECT n, c FROM t LEFT JOIN (SELECT l_quantity, count(*) AS c FROM lineitem GROUP BY l_quantity) ON l_quantity = n",
    "op_scalar_subquery": "SELECT count(*) AS n FROM customer WHERE c_acctbal > (SELECT avg(c_acctbal) FROM customer)",
    "op_conditional_sum": "SELECT l_linestatus, sum(CASE WHEN l_quantity > 25 THEN 1 ELSE 0 END) AS big FROM lineitem GROUP BY l_linestatus",
    "op_text_lengths": "SELECT lang, min(n_chars) AS low, max(n_chars) AS high FROM documents GROUP BY lang",
    "op_conversation_turns": "SELECT role, count(*) AS n, max(turn) AS last FROM conversations GROUP BY role",
}
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def _run(text: str):
    used = [t for t in TABLES if re.search(rf"\b{t}\b", text)]
    # a table is named only after FROM or JOIN; it becomes a parameter there
    marked = re.sub(r"\b(FROM|JOIN) (" + "|".join(used or ["-"]) + r")\b", r"\1 {\2}", text)

    def run(spark, sf_dir):
        frames = {t: spark.read.parquet(f"{sf_dir.rstrip('/')}/{t}.parquet") for t in used if "{" + t + "}" in marked}
        return spark.sql(marked, **frames)

    return run


def agg_argmin(spark, d):
    c = V.table(spark, d, "customer").groupBy("c_nationkey")
    return c.agg(F.min_by("c_custkey", F.struct("c_acctbal", "c_custkey")).alias("poorest"), F.max_by("c_custkey", F.struct("c_acctbal", "c_custkey")).alias("richest"))


def agg_pivot(spark, d):
    return V.table(spark, d, "events").groupBy("user_id").pivot("event_type", ["view", "click"]).count()


def agg_percentile(spark, d):
    return V.table(spark, d, "events").groupBy("event_type").agg(F.round(F.percentile("value", 0.5), 6).alias("median"), F.round(F.percentile("value", 0.9), 6).alias("p90"))


def collect_sorted(spark, d):
    o = V.table(spark, d, "orders").groupBy("o_custkey")
    return o.agg(F.array_join(F.array_sort(F.collect_list("o_orderkey")), ",").alias("orders"))


def hubs(spark, d):
    """The points that most other points have among their ten nearest."""
    into = N.reverse(N.knn_graph(V.emb(spark, d), 10)).groupBy("src").agg(F.count("*").alias("n"))
    return into.orderBy(F.desc("n"), "src").limit(10)


def degree_histogram(spark, d):
    """How many points have each in-degree in the graph of ten nearest neighbours, none included."""
    v = V.emb(spark, d)
    into = N.knn_graph(v, 10).groupBy(F.col("dst").alias("id")).agg(F.count("*").alias("n"))
    return v.select("id").join(into, "id", "left").groupBy(F.coalesce("n", F.lit(0)).alias("in_degree")).agg(F.count("*").alias("points"))


def join_sortmerge(spark, d):
    return V.table(spark, d, "orders").hint("merge").join(V.table(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n"))


def join_lateral_topk(spark, d):
    """The two dearest orders of each customer; a window that Spark limits before the shuffle."""
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    best = V.table(spark, d, "orders").withColumn("r", F.row_number().over(w)).where("r <= 2")
    return V.table(spark, d, "customer").join(best, F.col("c_custkey") == F.col("o_custkey")).select("c_custkey", "o_orderkey")


def array_ops(spark, d):
    x = F.col("vec")
    return V.emb(spark, d).select("id", F.size(x).alias("n"), F.round(F.array_max(x).cast("double"), 5).alias("high"), F.size(F.filter(x, lambda v: v > 0)).alias("positive"))


def map_ops(spark, d):
    c = V.table(spark, d, "conversations").groupBy("role").count().agg(F.map_from_entries(F.collect_list(F.struct("role", "count"))).alias("m"))
    return c.select(F.explode("m").alias("role", "n"))


def json_ops(spark, d):
    e = V.table(spark, d, "events").select(F.from_json("props", "k bigint")["k"].alias("k"))
    return e.groupBy("k").agg(F.count("*").alias("n"))


def date_ops(spark, d):
    o = V.table(spark, d, "orders")
    return o.groupBy(F.year("o_orderdate").alias("y"), F.quarter("o_orderdate").alias("q")).agg(F.count("*").alias("n"))


def stratified_sample(spark, d):
    """Five documents of each language, by a hash that any engine can compute."""
    w = Window.partitionBy("lang").orderBy(portable_hash("doc_id", 0), "doc_id")
    return V.table(spark, d, "documents").select("doc_id", "lang", F.row_number().over(w).alias("r")).where("r <= 5").select("doc_id", "lang")


HASHED = "((doc_id % 2147483648) * 1103515245 + 12345) % 2147483648"
NEAR = "WITH v AS (SELECT vec_id AS id, CAST(embedding AS DOUBLE[]) AS vec FROM embeddings), near AS (SELECT * FROM (SELECT q.id AS qid, b.id, row_number() OVER (PARTITION BY q.id ORDER BY list_distance(b.vec, q.vec), b.id) AS r FROM v b, v q WHERE b.id <> q.id) WHERE r <= 10)"
FRAMES = {
    "op_agg_argmin": (agg_argmin, "SELECT c_nationkey, arg_min(c_custkey, (c_acctbal, c_custkey)) AS poorest, arg_max(c_custkey, (c_acctbal, c_custkey)) AS richest FROM customer GROUP BY c_nationkey"),
    "op_agg_pivot": (agg_pivot, "SELECT user_id, nullif(count(*) FILTER (event_type = 'view'), 0) AS view, nullif(count(*) FILTER (event_type = 'click'), 0) AS click FROM events GROUP BY user_id"),
    "op_agg_percentile": (agg_percentile, "SELECT event_type, round(quantile_cont(value, 0.5), 6) AS median, round(quantile_cont(value, 0.9), 6) AS p90 FROM events GROUP BY event_type"),
    "op_collect_sorted": (collect_sorted, "SELECT o_custkey, string_agg(CAST(o_orderkey AS VARCHAR), ',' ORDER BY o_orderkey) AS orders FROM orders GROUP BY o_custkey"),
    "op_hubs": (hubs, NEAR + " SELECT id AS src, count(*) AS n FROM near GROUP BY id ORDER BY n DESC, id LIMIT 10"),
    "degree_histogram": (degree_histogram, NEAR + ", n AS (SELECT v.id, count(near.qid) AS c FROM v LEFT JOIN near ON near.id = v.id GROUP BY v.id) SELECT c AS in_degree, count(*) AS points FROM n GROUP BY c"),
    "op_join_sortmerge": (join_sortmerge, "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment"),
    "op_join_lateral_topk": (join_lateral_topk, "SELECT c_custkey, t.o_orderkey FROM customer, LATERAL (SELECT o_orderkey FROM orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 2) t"),
    "op_array_ops": (array_ops, "SELECT vec_id AS id, CAST(len(embedding) AS INT) AS n, round(list_max(CAST(embedding AS DOUBLE[])), 5) AS high, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INT) AS positive FROM embeddings"),
    "op_map_ops": (map_ops, "SELECT role, count(*) AS n FROM conversations GROUP BY role"),
    "op_json_ops": (json_ops, "SELECT CAST(regexp_extract(props, '\"k\": *([0-9]+)', 1) AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1"),
    "op_date_ops": (date_ops, "SELECT CAST(year(o_orderdate) AS INT) AS y, CAST(quarter(o_orderdate) AS INT) AS q, count(*) AS n FROM orders GROUP BY 1, 2"),
    "op_stratified_sample": (stratified_sample, f"SELECT doc_id, lang FROM (SELECT doc_id, lang, row_number() OVER (PARTITION BY lang ORDER BY {HASHED}, doc_id) AS r FROM documents) WHERE r <= 5"),
}


def queries() -> dict:
    return {n: _run(t) for n, t in STATEMENTS.items()} | {n: f for n, (f, _) in FRAMES.items()}


def oracle_sql() -> dict[str, str]:
    return {n: re.sub(r"sum\((CASE.*?END)\)", r"CAST(sum(\1) AS BIGINT)", t) for n, t in STATEMENTS.items()} | {n: t for n, (_, t) in FRAMES.items()}
