"""Registered queries of the graph engine, and SQL that says the same."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from . import catalog, stages
from . import workloads as X
from .functions import geometry as D
from .operators import index as I
from .operators import neighbors as N
from .sources import vectors as V
from .streaming import streams as S


def _emb(spark, d, n=None):
    e = V.emb(spark, d)
    return e if n is None else e.where(F.col("id") < n)


def _edges(index):
    return I.index_edges(index).select("src", "dst")


def flagship(spark, sf_dir):
    """Greedy search for indexed queries on the exact 60 degree graph: every answer is the point itself."""
    v = _emb(spark, sf_dir)
    ix = I.build_index(v, "exact_angle", alpha=60.0)
    q = X.queries_of(v.where("id % 10 = 7"))
    return N.precision_at_k(I.search_index(ix, q, 1, 1), N.exact_knn(v, q, 1), 1)


def _queries_ten(v):
    return X.queries_of(v.where("id % 10 = 3"))


def knn_exact_l2(spark, d):
    v = _emb(spark, d)
    return N.exact_knn(v.where("id % 10 <> 3"), _queries_ten(v), 10).select("qid", "rank", "id", F.round("dist", 6).alias("dist"))


def knn_exact_cosine(spark, d):
    """On unit vectors the cosine order is the Euclidean one."""
    v = V.normalize_l2(_emb(spark, d))
    got = N.exact_knn(v.where("id % 10 <> 3"), _queries_ten(v), 10)
    return got.select("qid", "rank", "id", F.round(F.col("dist") * F.col("dist") / 2, 6).alias("cosine_distance"))


def knn_exact_ip(spark, d):
    v = _emb(spark, d)
    return N.exact_ip(v.where("id % 10 <> 3"), _queries_ten(v), 10).select("qid", "rank", "id", F.round("ip", 6).alias("ip"))


def knn_graph_k10(spark, d):
    return N.knn_graph(_emb(spark, d), 10).select("src", "dst", "rank")


def range_search(spark, d):
    v = _emb(spark, d)
    return N.range_search(v.where("id % 10 <> 3"), _queries_ten(v), 1.2).select("qid", "id", F.round("dist", 6).alias("dist"))


def mutual_knn(spark, d):
    return N.mutual(N.knn_graph(_emb(spark, d), 10)).select("src", "dst")


def reverse_knn(spark, d):
    return N.reverse(N.knn_graph(_emb(spark, d), 10)).groupBy("src").agg(F.count("*").alias("n"))


def knn_filtered_label(spark, d):
    v = _emb(spark, d)
    return N.exact_knn(v.where("label = 3 and id % 10 <> 3"), _queries_ten(v), 5).select("qid", "rank", "id")


def lid_mle(spark, d):
    return N.lid_mle(N.knn_graph(_emb(spark, d), 20), 20).select("src", F.round("lid", 5).alias("lid"))


def conflict_rate(spark, d):
    return N.conflict_rate(_emb(spark, d, 64), 0.5)


def angle_graph(method, alpha, view):
    def run(spark, d):
        v = _emb(spark, d) if view == "emb" else V.part2(spark, d)
        return I.exact_graph(v, alpha if method == "exact_angle" else None).select("src", "dst")

    return run


def rng_exact(spark, d):
    """Undirected edges with no point at all in their lune: of the edges that lune pruning keeps, by an anti join on the pair table."""
    v = _emb(spark, d).select("id", "vec")
    some = I.index_edges(I.build_index(v, "mrng")).where("src < dst").select(F.col("src").alias("p"), F.col("dst").alias("q"))
    e = v.alias("a").join(v.alias("b"), F.col("a.id") != F.col("b.id")).select(F.col("a.id").alias("p"), F.col("b.id").alias("q"), D.l2_sq(F.col("a.vec"), F.col("b.vec")).alias("d2"))
    x, y, z = e.alias("x"), e.alias("y"), e.alias("z")
    half = e.join(some, ["p", "q"], "left_semi").alias("x")
    inside = half.join(y, F.col("x.p") == F.col("y.p")).join(z, (F.col("z.p") == F.col("y.q")) & (F.col("z.q") == F.col("x.q")))
    bad = inside.where((F.col("y.d2") < F.col("x.d2")) & (F.col("z.d2") < F.col("x.d2"))).select("x.p", "x.q").distinct()
    return half.select("p", "q").join(bad, ["p", "q"], "left_anti")


def lune_hash_order(spark, d):
    """Lune pruning of all other points, visited in an order that distance does not decide."""
    return I.exact_graph(_emb(spark, d), None, order="hash").select("src", "dst")


def truncate_degree(spark, d):
    ix = I.build_index(_emb(spark, d), "exact_angle", alpha=60.0)
    return N.truncate_graph(I.index_edges(ix), 8).select("src", "dst")


def truncate_neighbor_rank(spark, d):
    v = _emb(spark, d)
    ix = I.build_index(v, "exact_angle", alpha=60.0)
    return N.truncate_graph(I.index_edges(ix), 20, "neighbor_rank", N.knn_graph(v, 20)).select("src", "dst")


def monotonic_violations(spark, d):
    v = _emb(spark, d)
    return N.monotonic_violations(I.exact_graph(v, 60.0), v)


def degree_stats(spark, d):
    return N.degree_stats(I.exact_graph(_emb(spark, d), 60.0))


def two_hop_pool(spark, d):
    return N.two_hop_pool(N.knn_graph(_emb(spark, d), 10), 40)


def nag_forward(spark, d):
    v = _emb(spark, d)
    return N.angle_prune(N.two_hop_pool(N.knn_graph(v, 10), 40), v, 60.0, 32).select("src", "dst")


def nag_reverse_reprune(spark, d):
    v = _emb(spark, d)
    forward = N.angle_prune(N.two_hop_pool(N.knn_graph(v, 10), 40), v, 60.0, 32)
    return N.reverse_refine(forward, v, 60.0, 32).select("src", "dst")


def navigators(spark, d):
    return N.pick_navigators(_emb(spark, d), 10).select("node")


def entry_navigator(spark, d):
    v = _emb(spark, d)
    return N.entry_points(_queries_ten(v), N.pick_navigators(v, 10))


def reach_from_navigators(spark, d):
    v = _emb(spark, d)
    return N.reach(N.knn_graph(v, 10), N.pick_navigators(v, 3)).select("root", "node")


def sharded_merge(spark, d):
    v = _emb(spark, d)
    ix = I.build_index(v.where("id % 10 <> 3"), "scan", 4)
    return I.search_index(ix, _queries_ten(v), 10, 10).select("qid", "rank", "id", F.round("dist", 6).alias("dist"))


def greedy_indexed(spark, d):
    """Greedy search for points of the exact 60 degree graph always ends at the point."""
    v = _emb(spark, d)
    q = X.queries_of(v.where("id % 10 = 7"))
    return I.search_index(I.build_index(v, "exact_angle", alpha=60.0), q, 1, 1).select("qid", "id")


def eps_factor(spark, d):
    v = _emb(spark, d)
    base, q = v.where("id % 10 <> 3"), _queries_ten(v)
    truth = N.exact_knn(base, q, 10)
    skipped = N.exact_knn(base.where("id % 10 <> 5"), q, 10)
    return N.eps_factor(skipped, truth).select("qid", F.round("eps_1nn", 6).alias("eps_1nn"), F.round("eps_rank", 6).alias("eps_rank"))


def precision_at_k(spark, d):
    v = _emb(spark, d)
    base, q = v.where("id % 10 <> 3"), _queries_ten(v)
    return N.precision_at_k(N.exact_knn(base.where("id % 10 <> 5"), q, 10), N.exact_knn(base, q, 10), 10)


def part_knn(spark, d):
    v = V.part2(spark, d)
    return N.exact_knn(v.where("id % 10 <> 3"), _queries_ten(v), 5).select("qid", "rank", "id", F.round("dist", 4).alias("dist"))


def line_knn(spark, d):
    v = V.line4(spark, d)
    return N.exact_knn(v, X.queries_of(v.where("id % 997 = 3")), 5).select("qid", "rank", "id", F.round("dist", 2).alias("dist"))


def cust_vectors(spark, d):
    at = lambda i: F.get("vec", F.lit(i))
    return V.cust_vectors(spark, d).select("id", at(0).alias("x0"), F.round(at(1), 4).alias("x1"), at(3).alias("x3"))


def dedupe(spark, d):
    return V.dedupe_vectors(V.part2(spark, d))[1]


def nag_full(spark, d):
    return _edges(I.build_index(_emb(spark, d), "nag"))


def search_trace(spark, d):
    v = _emb(spark, d)
    return X.greedy_trace(v, X.queries_of(v.where("id % 50 = 7")), 60.0)


def step_monotonicity(spark, d):
    v = _emb(spark, d)
    base, q = X.base_and_queries(v)
    return X.step_monotonicity(X.greedy_trace(base, q, 60.0), base, N.exact_knn(base, q, 1))


def recall(method, size, floor, **params):
    return lambda spark, d: X.recall_gate(_emb(spark, d), method, size, floor, **params)


def tuned_curve(method, view):
    def run(spark, d):
        v = {"emb": lambda: _emb(spark, d), "docs": lambda: V.text_vectors(V.table(spark, d, "documents"), "doc_id", "text"), "pages": lambda: V.text_vectors(V.page_text(spark, d), "id", "text"), "cust": lambda: V.cust_vectors(spark, d)}[view]()
        return X.curve(v, method)

    return run


# Sizes and floors of the recall gates: search parameter, least precision on the embeddings.
GATES = {
    "nag": (120, 0.9), "nag_on_the_fly": (160, 0.8), "nav_mrng": (160, 0.85), "hnsw": (120, 0.85), "nsw": (120, 0.85), "knn_graph": (120, 0.9), "knn_graph_tree": (120, 0.9), "knn_graph_lsh": (120, 0.9), "pruned_knn": (160, 0.85),
    "diversified": (120, 0.9), "exact_angle": (120, 0.9), "mrng": (200, 0.8), "ivf_flat": (16, 0.99), "ivf_pq": (16, 0.2), "pq": (1, 0.2), "kd_forest": (400, 0.7),
    "kmeans_tree": (400, 0.7), "kd_kmeans_forest": (400, 0.7), "two_means_forest": (400, 0.7), "lsh": (400, 0.7), "spectral_hash": (400, 0.7), "scan": (0, 1.0),
}


def _line_some(spark, d):
    """Every row of the smaller tables; of the large one a nested hash sample, as in the growth experiment."""
    return V.sample_hash(V.line4(spark, d), 0.03)


def _workloads() -> dict:
    return {
        "w1_graph_stats": lambda s, d: X.w1_graph_stats(_emb(s, d)),
        "w2_density_cost": lambda s, d: X.w2_density_cost(V.part2(s, d).where("id <= 200")),
        "w3_routes": search_trace,
        "w5_index_table": lambda s, d: X.w5_index_table(_emb(s, d)),
        "w6_index_time": lambda s, d: X.w5_index_table(V.cust_vectors(s, d)).select("method", "n", "t1", "t2"),
        "w7_alpha_sweep": lambda s, d: X.w7_alpha_sweep(_emb(s, d)),
        "w8_grid": lambda s, d: X.w8_grid(_emb(s, d)),
        "w9_growth": lambda s, d: X.w9_growth(_line_some(s, d)),
        "w9_growth_fit": lambda s, d: X.fit_growth(X.w9_growth(_emb(s, d)), 20.0),
        "w10_sharded": lambda s, d: X.w10_sharded(_line_some(s, d)),
        "w11_on_the_fly": lambda s, d: X.w11_on_the_fly(_emb(s, d)),
        "w12_overlap": lambda s, d: X.w12_overlap(_emb(s, d)),
        "w13_lid": lambda s, d: X.w13_lid({"emb": _emb(s, d), "part2": V.part2(s, d), "cust": V.cust_vectors(s, d)}),
        "w14_doc_search": X.w14_doc_search,
        "w15_scan_share": lambda s, d: X.w15_scan_share(_emb(s, d)),
        "w16_filtered": lambda s, d: X.w16_filtered(_emb(s, d)),
        "delta_r": lambda s, d: X.delta_r(_emb(s, d)),
        "angle_histogram": lambda s, d: X.angle_histogram(_emb(s, d, 64)),
    }


def queries() -> dict:
    plain = (knn_exact_l2, knn_exact_cosine, knn_exact_ip, knn_graph_k10, range_search, mutual_knn, reverse_knn, knn_filtered_label, lid_mle, conflict_rate, rng_exact, lune_hash_order, truncate_degree, truncate_neighbor_rank, monotonic_violations, degree_stats, two_hop_pool, nag_forward, nag_reverse_reprune, navigators, entry_navigator, reach_from_navigators, sharded_merge, greedy_indexed, eps_factor, precision_at_k, part_knn, line_knn, cust_vectors, dedupe, nag_full, step_monotonicity)
    out = {f.__name__: f for f in plain}
    out |= {
        "angle_graph_60": angle_graph("exact_angle", 60.0, "emb"), "angle_graph_55": angle_graph("exact_angle", 55.0, "emb"), "angle_graph_alpha0": angle_graph("exact_angle", 0.0, "emb"),
        "angle_graph_30_part": angle_graph("exact_angle", 30.0, "part"), "mrng_exact": angle_graph("mrng", 60.0, "emb"), "mrng_part": angle_graph("mrng", 60.0, "part"),
    }
    out |= {f"recall_{m}": recall(m, *g) for m, g in GATES.items()}
    out |= {f"w4_curve_{m}": tuned_curve(m, "emb") for m in ("nag", "nav_mrng", "hnsw", "knn_graph", "diversified", "ivf_pq", "two_means_forest", "kd_kmeans_forest")}
    out |= {"w4_curve_docs_nag": tuned_curve("nag", "docs"), "w4_curve_pages_nag": tuned_curve("nag", "pages"), "w4_curve_cust_nag": tuned_curve("nag", "cust")}
    out |= _workloads()
    out |= {"stream_tumbling": S.tumbling, "stream_sliding": S.sliding, "stream_sessions": S.sessions, "stream_dedupe": S.deduplicated, "stream_static_join": S.static_join}
    return out | stages.queries() | catalog.queries()


EMB = "SELECT vec_id AS id, CAST(embedding AS DOUBLE[]) AS vec, label FROM embeddings"
PART = "SELECT p_partkey AS id, [CAST(p_size * 20 AS DOUBLE), round((p_retailprice - 900) * 10)] AS vec FROM part"
HASH = "((id % 2147483648) * 1103515245 + 12345) % 2147483648"


def _knn_sql(base: str, asks: str, k: int, view: str = EMB, measure: str = "list_distance(b.vec, q.vec)") -> str:
    return f"""v AS ({view}), near AS (SELECT qid, id, dist, rank FROM (
      SELECT q.id AS qid, b.id AS id, {measure} AS dist, row_number() OVER (PARTITION BY q.id ORDER BY {measure}, b.id) AS rank
      FROM (SELECT * FROM v WHERE {base}) b, (SELECT * FROM v WHERE {asks}) q WHERE NOT (b.id = q.id AND '{asks}' = 'true')) WHERE rank <= {k})"""


def _fold_steps(conflict: str, cap: int | None = None, among: str = "", name: str = "", order: str = "d2, q") -> str:
    """The greedy rule, one kept edge of every point a round: the first candidate left stays and takes those it blocks away."""
    stop = f" AND x.k < {cap}" if cap else ""
    mine = ", ".join(f"x.{c.strip()}" if c.strip() in ("d2", "q") else c.replace("(id ", "(x.q ") for c in order.split(","))
    return f"""c{name} AS (SELECT p, q, d2, row_number() OVER (PARTITION BY p ORDER BY {order.replace("(id ", "(q ")}) AS rk FROM e {among}),
    f{name} AS (SELECT p, q, d2, rk AS r, 1 AS k FROM c{name}
      UNION ALL SELECT x.p, x.q, x.d2, row_number() OVER (PARTITION BY x.p ORDER BY {mine}) AS r, x.k + 1 FROM f{name} x JOIN f{name} y ON x.p = y.p AND y.r = 1
        JOIN e z ON z.p = x.q AND z.q = y.q WHERE x.r > 1{stop} AND NOT ({conflict})),
    g{name} AS (SELECT p AS src, q AS dst, d2 FROM f{name} WHERE r = 1)"""


ALL_PAIRS = "e AS MATERIALIZED (SELECT a.id AS p, b.id AS q, pow(list_distance(a.vec, b.vec), 2) AS d2 FROM v a, v b WHERE a.id <> b.id)"


def _fold_sql(view: str, where: str, conflict: str, cap: int | None = None, order: str = "d2, q") -> str:
    return f"WITH RECURSIVE v AS (SELECT id, vec FROM ({view}) WHERE {where}), {ALL_PAIRS}, {_fold_steps(conflict, cap, order=order)}"


def _angle(cos: float) -> str:
    return f"y.d2 + x.d2 - z.d2 > 2 * sqrt(y.d2) * sqrt(x.d2) * CAST({cos!r} AS DOUBLE)"


LUNE = "y.d2 < x.d2 AND z.d2 < x.d2"
G60 = _fold_sql(EMB, "true", _angle(0.5))


def oracle_sql() -> dict[str, str]:
    ten = ("id % 10 <> 3", "id % 10 = 3")
    graph10 = _knn_sql("true", "true", 10)
    out = {
        "knn_exact_l2": f"WITH {_knn_sql(*ten, 10)} SELECT qid, rank, id, round(dist, 6) AS dist FROM near",
        "knn_exact_ip": f"WITH {_knn_sql('id % 10 <> 3', 'id % 10 = 3', 10, measure='-list_dot_product(b.vec, q.vec)')} SELECT qid, rank, id, round(-dist, 6) AS ip FROM near",
        "knn_exact_cosine": f"WITH {_knn_sql(*ten, 10, measure='1 - list_cosine_similarity(b.vec, q.vec)')} SELECT qid, rank, id, round(dist, 6) AS cosine_distance FROM near",
        "knn_graph_k10": f"WITH {graph10} SELECT qid AS src, id AS dst, rank FROM near",
        "range_search": f"WITH v AS ({EMB}) SELECT q.id AS qid, b.id, round(list_distance(b.vec, q.vec), 6) AS dist FROM v b, v q WHERE b.id % 10 <> 3 AND q.id % 10 = 3 AND list_distance(b.vec, q.vec) < 1.2",
        "mutual_knn": f"WITH {graph10} SELECT a.qid AS src, a.id AS dst FROM near a JOIN near b ON a.qid = b.id AND a.id = b.qid",
        "reverse_knn": f"WITH {graph10} SELECT id AS src, count(*) AS n FROM near GROUP BY id",
        "knn_filtered_label": f"WITH {_knn_sql('label = 3 AND id % 10 <> 3', 'id % 10 = 3', 5)} SELECT qid, rank, id FROM near",
        "lid_mle": f"WITH {_knn_sql('true', 'true', 20)}, far AS (SELECT qid, dist AS dk FROM near WHERE rank = 20) SELECT near.qid AS src, round(-1 / avg(ln(dist / dk)), 5) AS lid FROM near JOIN far ON near.qid = far.qid WHERE rank < 20 AND dist > 0 GROUP BY near.qid",
        "conflict_rate": f"WITH v AS (SELECT * FROM ({EMB}) WHERE id < 64), e AS (SELECT a.id AS p, b.id AS q, pow(list_distance(a.vec, b.vec), 2) AS d2 FROM v a, v b WHERE a.id <> b.id) SELECT round(avg(CASE WHEN {_angle(0.5)} THEN 1.0 ELSE 0.0 END), 9) AS rate, count(*) AS n FROM e x JOIN e y ON x.p = y.p AND x.q < y.q JOIN e z ON z.p = x.q AND z.q = y.q",
        "rng_exact": f"WITH v AS (SELECT * FROM ({EMB})), e AS (SELECT a.id AS p, b.id AS q, list_distance(a.vec, b.vec) AS d FROM v a, v b WHERE a.id <> b.id) SELECT x.p, x.q FROM e x WHERE x.p < x.q AND NOT EXISTS (SELECT 1 FROM e y JOIN e z ON z.p = y.q WHERE y.p = x.p AND z.q = x.q AND y.d < x.d AND z.d < x.d)",
        "angle_graph_60": G60 + " SELECT src, dst FROM g",
        "angle_graph_55": _fold_sql(EMB, "true", _angle(D.cos_degrees(55.0))) + " SELECT src, dst FROM g",
        "angle_graph_alpha0": "SELECT a.vec_id AS src, b.vec_id AS dst FROM embeddings a, embeddings b WHERE a.vec_id <> b.vec_id",
        "angle_graph_30_part": _fold_sql(PART, "true", _angle(D.cos_degrees(30.0))) + " SELECT src, dst FROM g",
        "mrng_exact": _fold_sql(EMB, "true", LUNE) + " SELECT src, dst FROM g",
        "lune_hash_order": _fold_sql(EMB, "true", LUNE, order=f"{HASH}, q") + " SELECT src, dst FROM g",
        "mrng_part": _fold_sql(PART, "true", LUNE) + " SELECT src, dst FROM g",
        "truncate_degree": G60 + " SELECT src, dst FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY d2, dst) AS r FROM g) WHERE r <= 8",
        "truncate_neighbor_rank": G60 + " SELECT g.src, g.dst FROM g JOIN c ON g.src = c.p AND g.dst = c.q WHERE c.rk <= 20",
        "monotonic_violations": "SELECT vec_id AS p, vec_id AS q FROM embeddings WHERE false",
        "degree_stats": G60 + ", n AS (SELECT src, count(*) AS c FROM g GROUP BY src) SELECT round(avg(c), 6) AS aod, max(c) AS mod, CAST(sum(c) AS BIGINT) AS n_edges FROM n",
        "two_hop_pool": f"WITH {graph10}, every AS (SELECT qid AS src, id AS cand, rank AS via FROM near UNION ALL SELECT a.qid, b.id, a.rank FROM near a JOIN near b ON a.id = b.qid WHERE b.id <> a.qid), first AS (SELECT src, cand, min(via) AS via_rank FROM every GROUP BY src, cand), per AS (SELECT src, via_rank, count(*) AS c FROM first GROUP BY src, via_rank), cut AS (SELECT src, via_rank, coalesce(sum(c) OVER (PARTITION BY src ORDER BY via_rank ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM per) SELECT first.src, cand, first.via_rank FROM first JOIN cut ON first.src = cut.src AND first.via_rank = cut.via_rank WHERE before < 40",
        "navigators": f"SELECT id AS node FROM ({EMB}) ORDER BY {HASH}, id LIMIT 10",
        "entry_navigator": f"WITH v AS ({EMB}), m AS (SELECT id, vec FROM v ORDER BY {HASH}, id LIMIT 10) SELECT qid, entry FROM (SELECT v.id AS qid, m.id AS entry, row_number() OVER (PARTITION BY v.id ORDER BY list_distance(v.vec, m.vec), m.id) AS r FROM v, m WHERE v.id % 10 = 3) WHERE r = 1",
        "reach_from_navigators": f"WITH RECURSIVE {graph10}, roots AS (SELECT id FROM v ORDER BY {HASH}, id LIMIT 3), r AS (SELECT id AS root, id AS node FROM roots UNION SELECT r.root, near.id FROM r JOIN near ON near.qid = r.node) SELECT root, node FROM r",
        "sharded_merge": f"WITH {_knn_sql(*ten, 10)} SELECT qid, rank, id, round(dist, 6) AS dist FROM near",
        "greedy_indexed": "SELECT vec_id AS qid, vec_id AS id FROM embeddings WHERE vec_id % 10 = 7",
        "precision_at_k": f"WITH {_knn_sql(*ten, 10)}, less AS (SELECT qid, id, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS r FROM (SELECT q.id AS qid, b.id, list_distance(b.vec, q.vec) AS dist FROM v b, v q WHERE b.id % 10 NOT IN (3, 5) AND q.id % 10 = 3)) SELECT near.qid, count(less.id) / CAST(10 AS DOUBLE) AS precision FROM near LEFT JOIN less ON near.qid = less.qid AND near.id = less.id AND less.r <= 10 GROUP BY near.qid",
        "eps_factor": f"WITH {_knn_sql(*ten, 10)}, less AS (SELECT qid, id, dist, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS rank FROM (SELECT q.id AS qid, b.id, list_distance(b.vec, q.vec) AS dist FROM v b, v q WHERE b.id % 10 NOT IN (3, 5) AND q.id % 10 = 3)), one AS (SELECT qid, dist AS d1 FROM near WHERE rank = 1) SELECT less.qid, round(max(less.dist / d1 - 1), 6) AS eps_1nn, round(max(less.dist / near.dist - 1), 6) AS eps_rank FROM less JOIN near ON less.qid = near.qid AND less.rank = near.rank JOIN one ON one.qid = less.qid GROUP BY less.qid",
        "part_knn": f"WITH {_knn_sql('id % 10 <> 3', 'id % 10 = 3', 5, PART)} SELECT qid, rank, id, round(dist, 4) AS dist FROM near",
        "dedupe": f"WITH v AS ({PART}) SELECT id, min(id) OVER (PARTITION BY vec) AS rep FROM v",
        "cust_vectors": "WITH l AS (SELECT l_orderkey, sum(l_extendedprice) AS price, sum(l_discount) AS disc, sum(CASE WHEN l_returnflag = 'R' THEN 1 ELSE 0 END) AS back, count(*) AS n FROM lineitem GROUP BY l_orderkey), o AS (SELECT o_custkey, count(*) AS orders, sum(price) AS price, sum(disc) AS disc, sum(back) AS back, sum(n) AS n FROM orders JOIN l ON o_orderkey = l_orderkey GROUP BY o_custkey) SELECT c_custkey AS id, orders / CAST(40 AS DOUBLE) AS x0, round(price / n / 100000, 4) AS x1, CAST(back AS DOUBLE) / n AS x3 FROM o JOIN customer ON o_custkey = c_custkey",
        "stream_tumbling": "SELECT CAST(epoch(date_trunc('day', ts)) AS BIGINT) AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1, 2",
        "stream_dedupe": "SELECT DISTINCT user_id, event_type FROM events",
        "stream_static_join": "SELECT event_id, c_name FROM events JOIN customer ON user_id = c_custkey",
    }
    out |= {f"recall_{m}": "SELECT true AS precise, true AS complete" for m in GATES}
    return out | stages.oracle_sql() | catalog.oracle_sql()
