"""Registered queries of single stages, baselines by name, timed measures, SQL surface and stateful streams."""

from __future__ import annotations

from pyspark.sql import functions as F

from . import measures as M
from . import workloads as X
from .functions import surface
from .functions.geometry import cos_degrees
from .operators import index as I
from .operators import neighbors as N
from .operators import relational as R
from .plans.lineage import cut
from .sources import vectors as V
from .sources import words as W
from .streaming import stateful as T


def _emb(spark, d, n=None):
    e = V.emb(spark, d)
    return e if n is None else e.where(F.col("id") < n)


def range_band_join(spark, d):
    """Pairs of different vectors by their smallest ids, and each further copy with the smallest id of its vector."""
    reps, copies = V.dedupe_vectors(V.part2(spark, d))
    pairs = R.grid_range_join(reps, reps, 50.0, 2).where("id < other").select("id", "other", "dist2")
    return pairs.unionAll(copies.where("id <> rep").select("rep", "id", F.lit(0.0)))


def angle_graph_per_node_alpha(spark, d):
    v = _emb(spark, d).withColumn("alpha", F.when(F.col("id") % 2 == 0, 45.0).otherwise(60.0))
    return I.exact_graph(v, "alpha").select("src", "dst")


def alpha_for_degree(spark, d):
    return I.exact_alpha_for_degree(_emb(spark, d), 12)


def two_hop_pool_capped(spark, d):
    v = _emb(spark, d)
    return R.nearest_of_pool(N.two_hop_pool(N.knn_graph(v, 10), 40), v, 40)


def nag_reverse_insert(spark, d):
    return I.index_edges(I.build_index(_emb(spark, d), "nag", reverse="insert")).select("src", "dst")


def connectors(spark, d):
    """Links that join the parts of a graph of five neighbours, by its builder's count."""
    return I.build_index(_emb(spark, d), "nag", k=5, l=10, r=8).select("shard", "n", "links", "max_degree")


def _exact60(spark, d, n=None):
    v = _emb(spark, d, n)
    return v, cut(I.exact_graph(v, 60.0))


def greedy_route(spark, d):
    """Greedy frontier search by joins on the exact graph: a point of the graph finds itself."""
    v, e = _exact60(spark, d)
    q = X.queries_of(v.where("id % 10 = 7"))
    return R.frontier_search(e, v, q, N.entry_points(q, N.pick_navigators(v, 3)), 1, 1).select("qid", "id")


def pool_search(spark, d):
    v = _emb(spark, d)
    base, q = v.where("id % 10 <> 3"), X.queries_of(v.where("id % 50 = 3"))
    e = cut(I.exact_graph(base, 60.0))
    return R.frontier_search(e, base, q, N.entry_points(q, N.pick_navigators(base, 3)), 5, 15).select("qid", "rank", "id")


def search_trace(spark, d):
    v = _emb(spark, d)
    return X.greedy_trace(v, X.queries_of(v.where("id % 25 = 7")), 60.0)


def path_length(indexed):
    def run(spark, d):
        base, un = X.base_and_queries(_emb(spark, d))
        q = X.queries_of(base.where("id % 10 = 7")) if indexed else un
        return X.measured(I.build_index(base, "exact_angle", alpha=60.0), q, N.exact_knn(base, q, 1), 1, 1).select("hops", "n_dist", "precision")

    return run


def answers(method, size, shards=1, **params):
    def run(spark, d):
        base, q = X.base_and_queries(_emb(spark, d))
        return I.search_index(I.build_index(base, method, shards, **params), q, 10, size).select("qid", "rank", "id")

    return run


def nn_descent(spark, d):
    """Whether lists of neighbours of neighbours hold nine in ten of the exact ones."""
    v = _emb(spark, d)
    edges = I.index_edges(I.build_index(v, "knn_graph", k=10, knn="nn_descent")).select("src", "dst")
    exact = N.knn_graph(v, 10).select("src", "dst")
    hit = exact.join(edges, ["src", "dst"], "left_semi").agg(F.count("*").alias("h"))
    return hit.crossJoin(exact.agg(F.count("*").alias("n"))).select((F.col("h") >= 0.9 * F.col("n")).alias("precise"))


def word_vectors(spark, d):
    c = W.word_counts(V.table(spark, d, "documents"))
    x = F.log1p(F.col("c").cast("double"))
    return c.groupBy("word").agg(F.sum("c").alias("uses"), F.count("*").alias("filled"), F.round(F.sum(x * x), 4).alias("norm2")).where("uses >= 5")


def word_neighbors(spark, d):
    v = W.word_vectors(V.table(spark, d, "documents"), least=50)
    return N.exact_knn(v, X.queries_of(v.where("id % 20 = 0")), 5).select("qid", "rank", "id")


def vector_mean(spark, d):
    return R.vector_mean(V.emb(spark, d), "label").select("label", "pos", F.round("mean", 6).alias("mean"))


def sql_functions(spark, d):
    surface.register(spark)
    V.emb(spark, d).createOrReplaceTempView("sql_vectors")
    return spark.sql("SELECT a.id AS p, b.id AS q, round(vec_l2(a.vec, b.vec), 6) AS dist, round(vec_dot(a.vec, b.vec), 6) AS ip FROM sql_vectors a JOIN sql_vectors b ON b.id = a.id + 1")


def sql_table_function(spark, d):
    """The ten nearest of the point 3, from four scanned shards, in SQL alone."""
    surface.register(spark)
    base, _ = X.base_and_queries(_emb(spark, d))
    I.build_index(base, "scan", 4).select("shard", "blob").createOrReplaceTempView("sql_shards")
    V.emb(spark, d).createOrReplaceTempView("sql_vectors")
    vec = spark.sql("SELECT vec FROM sql_vectors WHERE id = 3").first()["vec"]
    given = ", ".join(f"{float(x)!r}D" for x in vec)
    return spark.sql(f"SELECT id, round(dist, 6) AS dist FROM nearest_in_shards(TABLE(SELECT shard, blob FROM sql_shards), array({given}), 10, 10) ORDER BY dist, id LIMIT 10")


TIMED = ("nag", "nav_mrng", "hnsw", "ivf_pq", "scan")


def search_rates(spark, d):
    v = _emb(spark, d)
    return X._union(X._together(lambda m: M.rate_curve(v, m), list(TIMED)))  # built at once; timed when the rows are asked for


def search_speedup(spark, d):
    v = _emb(spark, d)
    return M.speedup(X._union([M.rate_curve(v, m) for m in ("nag", "nav_mrng", "scan")]), "scan", 0.9)


def _some_lines(spark, d):
    return V.sample_hash(V.line4(spark, d), 0.03)


def queries() -> dict:
    plain = (range_band_join, angle_graph_per_node_alpha, alpha_for_degree, two_hop_pool_capped, nag_reverse_insert, connectors, greedy_route, pool_search, search_trace, nn_descent, word_vectors, word_neighbors, vector_mean, sql_functions, sql_table_function, search_rates, search_speedup)
    out = {f.__name__: f for f in plain}
    out |= {"path_length_indexed": path_length(True), "path_length_unindexed": path_length(False), "sharded_nag_search": answers("nag", 60, 4), "nag_on_the_fly": answers("nag_on_the_fly", 160)}
    out |= {"scan": answers("scan", 0), "ivf_flat": answers("ivf_flat", I.DEFAULTS["nlists"]), "ivf_pq": answers("ivf_pq", 16), "pq_adc": answers("pq", 1), "knn_graph_search": answers("knn_graph", 120), "diversified_knn": answers("diversified", 120)}
    out |= {m: answers(m, s) for m, s in (("two_means_forest", 400), ("kd_kmeans_forest", 400), ("nav_mrng", 160), ("hnsw", 120), ("lsh", 400))}
    out |= {
        "w4_curve_words_nag": lambda s, d: X.curve(W.word_vectors(V.table(s, d, "documents"), least=200), "nag"),
        "w4_curve_line_nag": lambda s, d: X.curve(_some_lines(s, d), "nag"),
        "w6_build_memory": lambda s, d: M.build_memory(_emb(s, d).select("id", "vec")),
        "stream_stateful": T.last_events, "stream_interval_join": T.views_and_clicks,
    }
    return out


def oracle_sql() -> dict[str, str]:
    from .queries import ALL_PAIRS, EMB, PART, _angle, _fold_sql, _fold_steps, _knn_sql

    ten = _knn_sql("id % 10 <> 3", "id % 10 = 3", 10)
    near = f"WITH {ten} SELECT qid, rank, id FROM near"
    wide, narrow = repr(cos_degrees(45.0)), repr(cos_degrees(60.0))
    mixed = f"y.d2 + x.d2 - z.d2 > 2 * sqrt(y.d2) * sqrt(x.d2) * CAST(CASE WHEN x.p % 2 = 0 THEN {wide} ELSE {narrow} END AS DOUBLE)"
    pool = f"{_knn_sql('true', 'true', 10)}, every AS (SELECT qid AS src, id AS cand, rank AS via FROM near UNION ALL SELECT a.qid, b.id, a.rank FROM near a JOIN near b ON a.id = b.qid WHERE b.id <> a.qid), firsts AS (SELECT src, cand, min(via) AS via_rank FROM every GROUP BY src, cand), per AS (SELECT src, via_rank, count(*) AS c FROM firsts GROUP BY src, via_rank), cuts AS (SELECT src, via_rank, coalesce(sum(c) OVER (PARTITION BY src ORDER BY via_rank ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM per), pools AS (SELECT f.src, f.cand FROM firsts f JOIN cuts c ON f.src = c.src AND f.via_rank = c.via_rank WHERE before < 40)"
    forward = _fold_steps(_angle(0.5), 32, "JOIN pools ON pools.src = e.p AND pools.cand = e.q", "1")
    both = "JOIN (SELECT src, dst FROM g1 UNION SELECT dst, src FROM g1) m ON m.src = e.p AND m.dst = e.q"
    tokens = r"list_filter(regexp_split_to_array(lower(text), '[^\p{L}]+'), lambda t: t <> '')"
    h = "CAST('0x' || substr(md5({w}), 1, 4) AS INT) % 64"
    ahead = lambda s: f"SELECT unnest(list_zip(t[1:len(t) - {s}], t[{s + 1}:])) AS p FROM d WHERE len(t) > {s}"
    return {
        "range_band_join": f"WITH v AS ({PART}), m AS (SELECT id, vec, min(id) OVER (PARTITION BY vec) AS rep FROM v), r AS (SELECT id, vec FROM m WHERE id = rep) SELECT a.id, b.id AS other, pow(a.vec[1] - b.vec[1], 2) + pow(a.vec[2] - b.vec[2], 2) AS dist2 FROM r a JOIN r b ON a.id < b.id WHERE pow(a.vec[1] - b.vec[1], 2) + pow(a.vec[2] - b.vec[2], 2) <= 2500 UNION ALL SELECT rep, id, CAST(0 AS DOUBLE) FROM m WHERE id <> rep",
        "angle_graph_per_node_alpha": _fold_sql(EMB, "true", mixed) + " SELECT src, dst FROM g",
        "two_hop_pool_capped": f"WITH {pool} SELECT src, cand FROM (SELECT src, cand, row_number() OVER (PARTITION BY src ORDER BY list_distance(a.vec, b.vec), cand) AS r FROM pools JOIN v a ON a.id = src JOIN v b ON b.id = cand) WHERE r <= 40",
        "nag_forward": f"WITH RECURSIVE {pool}, {ALL_PAIRS}, {forward} SELECT src, dst FROM g1",
        "nag_reverse_reprune": f"WITH RECURSIVE {pool}, {ALL_PAIRS}, {forward}, {_fold_steps(_angle(0.5), 32, both, '2')} SELECT src, dst FROM g2",
        "greedy_route": "SELECT vec_id AS qid, vec_id AS id FROM embeddings WHERE vec_id % 10 = 7",
        "scan": near,
        "ivf_flat": near,
        "nn_descent": "SELECT true AS precise",
        "vector_mean": f"SELECT label, CAST(pos - 1 AS INT) AS pos, round(avg(x), 6) AS mean FROM (SELECT label, unnest(vec) AS x, unnest(range(1, len(vec) + 1)) AS pos FROM ({EMB})) GROUP BY label, pos",
        "sql_functions": f"WITH v AS ({EMB}) SELECT a.id AS p, b.id AS q, round(list_distance(a.vec, b.vec), 6) AS dist, round(list_dot_product(a.vec, b.vec), 6) AS ip FROM v a JOIN v b ON b.id = a.id + 1",
        "sql_table_function": f"WITH {ten} SELECT id, round(dist, 6) AS dist FROM near WHERE qid = 3",
        "word_vectors": f"WITH d AS (SELECT {tokens} AS t FROM documents), p AS ({ahead(1)} UNION ALL {ahead(2)}), b AS (SELECT p[1] AS word, p[2] AS other FROM p UNION ALL SELECT p[2], p[1] FROM p), c AS (SELECT word, {h.format(w='other')} AS at, count(*) AS c FROM b GROUP BY 1, 2) SELECT word, CAST(sum(c) AS BIGINT) AS uses, count(*) AS filled, round(sum(pow(ln(1 + c), 2)), 4) AS norm2 FROM c GROUP BY word HAVING sum(c) >= 5",
        "stream_stateful": "SELECT user_id, count(*) AS n, array_to_string(list_reverse(list_slice(list(event_id ORDER BY event_id DESC), 1, 3)), ',') AS last FROM events GROUP BY user_id",
        "stream_interval_join": "SELECT a.event_id AS viewed, b.event_id AS clicked FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR WHERE a.event_type = 'view' AND b.event_type = 'click'",
    }
