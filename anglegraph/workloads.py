"""The experiments on the given tables: one function for each, with counted (not timed) results.

Times and bytes stand in their own columns. Sizes are those of the tables; graph-complete work is
restricted to the point sets named in each workload, as its cost grows with the square of n.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .functions.geometry import cos_degrees
from .operators import index as I
from .operators import neighbors as N
from .plans.lineage import cut
from .sources import vectors as V


def queries_of(vectors: DataFrame) -> DataFrame:
    return vectors.select(F.col("id").alias("qid"), "vec")


def base_and_queries(vectors: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Nine tenths as base, one tenth as unindexed queries."""
    return vectors.where("id % 10 <> 3").select("id", "vec"), queries_of(vectors.where("id % 10 = 3"))


def measured(index: DataFrame, queries: DataFrame, truth: DataFrame, k: int, size: int, **more) -> DataFrame:
    """One row: precision, and per query the distances, expansions and hops."""
    raw = I.search_shards(index, queries, k, size, **more)
    w = Window.partitionBy("qid").orderBy("dist", "id")
    raw = raw.withColumn("rank", F.row_number().over(w))
    t = truth.where(F.col("rank") <= k).select("qid", "id", F.lit(1).alias("hit"))
    d = raw.join(t, ["qid", "id"], "left")
    per = d.groupBy("qid").agg((F.sum(F.when(F.col("rank") <= k, F.coalesce("hit", F.lit(0))).otherwise(0)) / k).alias("p"), F.sum("n_dist").alias("n"), F.sum("expansions").alias("e"), F.sum("hops").alias("h"))
    return per.agg(F.avg("p").alias("precision"), F.avg("n").alias("n_dist"), F.avg("e").alias("expansions"), F.avg("h").alias("hops"), F.count("*").alias("n_queries"))


def _labelled(df: DataFrame, **labels) -> DataFrame:
    return df.select(*[F.lit(v).alias(k) for k, v in labels.items()], *df.columns)


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def _together(work, items: list) -> list:
    """The results for the items, from threads, as the jobs of one leave most tasks' slots free."""
    from concurrent.futures import ThreadPoolExecutor

    from pyspark import inheritable_thread_target

    with ThreadPoolExecutor(len(items)) as pool:
        return [f.result() for f in [pool.submit(inheritable_thread_target(work), x) for x in items]]


SWEEP = {m: (10, 20, 40, 80) for m in I.GRAPHS} | {m: (1, 2, 4, 8, 16) for m in ("ivf_flat", "ivf_pq", "pq")} | {m: (50, 100, 200, 400) for m in ("kd_forest", "kmeans_tree", "kd_kmeans_forest", "two_means_forest", "lsh", "spectral_hash")} | {"scan": (0,)}


def curve(vectors: DataFrame, method: str, k: int = 10, **params) -> DataFrame:
    """Precision against distances as the method's search parameter rises."""
    base, q = base_and_queries(vectors)
    truth = cut(N.exact_knn(base, q, k))
    ix = I.build_index(base, method, **params)
    return _union([_labelled(measured(ix, q, truth, k, s), method=method, size=s) for s in SWEEP[method]])


def w1_graph_stats(vectors: DataFrame, caps=(10, 20)) -> DataFrame:
    """Degrees and hops to indexed and unindexed queries, of exact graphs and their truncations."""
    base, un = base_and_queries(vectors)
    ind = queries_of(base.where("id % 10 = 7"))
    out = []
    for name, method, alpha in (("mrng", "mrng", 60.0), ("angle60", "exact_angle", 60.0), ("angle55", "exact_angle", 55.0), ("angle50", "exact_angle", 50.0)):
        ix = I.build_index(base, method, alpha=alpha)
        deg = N.degree_stats(I.index_edges(ix))
        hops = [measured(ix, q, N.exact_knn(base, q, 1), 1, 1).select(F.col("hops").alias(f"hops_{n}"), F.col("precision").alias(f"precision_{n}")) for n, q in (("indexed", ind), ("unindexed", un))]
        out.append(_labelled(deg.crossJoin(hops[0]).crossJoin(hops[1]), graph=name))  # one row each
        if name in ("angle60", "angle50"):
            for cap in caps:
                cut = N.degree_stats(N.truncate_graph(I.index_edges(ix), cap))
                none = [F.lit(None).cast("double").alias(c) for c in ("hops_indexed", "precision_indexed", "hops_unindexed", "precision_unindexed")]
                out.append(_labelled(cut.select("*", *none), graph=f"{name}_cut{cap}"))
    return _union(out)


def w2_density_cost(vectors: DataFrame) -> DataFrame:
    """Distances to indexed queries on graphs from sparse to complete."""
    pts = vectors.select("id", "vec")
    q = queries_of(pts.where("id % 5 = 0"))
    truth = N.exact_knn(pts, q, 1)
    out = []
    for name, method, alpha in (("mrng", "mrng", 60.0), ("angle60", "exact_angle", 60.0), ("angle30", "exact_angle", 30.0), ("angle0", "exact_angle", 0.0)):
        ix = I.build_index(pts, method, alpha=alpha)
        out.append(_labelled(measured(ix, q, truth, 1, 1).crossJoin(N.degree_stats(I.index_edges(ix))), graph=name))
    return _union(out)


def w5_index_table(vectors: DataFrame, **params) -> DataFrame:
    """Edges, degrees and bytes of each graph index on one point set, with w6's build seconds."""
    parts = _together(lambda m: I.build_index(vectors, m, **params).select("method", "n", "n_edges", "max_degree", "links", "t1", "t2"), ["nag", "nav_mrng", "hnsw", "knn_graph", "diversified"])
    d = _union(parts)
    return d.withColumn("aod", F.col("n_edges") / F.col("n")).withColumn("bytes_matrix", F.col("n") * F.col("max_degree") * 4).withColumn("bytes_ragged", F.col("n_edges") * 4)


def w7_alpha_sweep(vectors: DataFrame, alphas=(30.0, 50.0, 55.0, 60.0, 65.0, 70.0, 80.0)) -> DataFrame:
    """Degree, monotone violations and search cost as the angle rises."""
    base, q = base_and_queries(vectors)
    truth = N.exact_knn(base, q, 10)
    out = []
    for a in alphas:
        ix = I.build_index(base, "exact_angle", alpha=a)
        e = I.index_edges(ix)
        bad = I.index_violations(ix)
        out.append(_labelled(measured(ix, q, truth, 10, 20).crossJoin(N.degree_stats(e)).crossJoin(bad), alpha=a))
    return _union(out)


def w8_grid(vectors: DataFrame, target: float = 0.9) -> DataFrame:
    """Validation on one point in a hundred: the cheapest parameters that reach the precision."""
    train, valid = V.split(vectors)
    q = queries_of(valid)
    truth = N.exact_knn(train, q, 10)
    grid = [{"l": pool, "r": r, "alpha": alpha} for pool in (40, 80) for r in (16, 32) for alpha in (50.0, 60.0)]
    built = _together(lambda p: I.build_index(train, "nag", **p), grid)
    out = [_labelled(measured(ix, q, truth, 10, size), **p, size=size) for p, ix in zip(grid, built) for size in (20, 60)]
    w = Window.orderBy((F.col("precision") < target).cast("int"), "n_dist", "l", "r", "alpha")
    return _union(out).withColumn("place", F.row_number().over(w))  # 16 rows


def search_to_precision(index, queries, truth, k: int, target: float, sizes=(10, 20, 40, 80, 160, 320)) -> dict:
    """The smallest pool that reaches the target, and its row; the largest pool where none does."""
    for s in sizes:
        row = measured(index, queries, truth, k, s).first().asDict() | {"size": s}
        if row["precision"] >= target:
            break
    return row


def w9_growth(vectors: DataFrame, fractions=(0.125, 0.25, 0.5, 1.0)) -> DataFrame:
    """Cost of search at 99 % precision and of edges, against n, on nested subsets."""
    spark = vectors.sparkSession
    rows = []
    for f in fractions:
        some = V.sample_hash(vectors, f)
        base, q = base_and_queries(some)
        ix = I.build_index(base, "nag")
        built = ix.select("n", "n_edges", "t2").first()
        got = search_to_precision(ix, q.limit(50), N.exact_knn(base, q.limit(50), 10), 10, 0.99)
        rows.append((f, built["n"], built["n_edges"], built["t2"], got["size"], got["precision"], got["n_dist"]))
    return spark.createDataFrame(rows, "fraction double, n long, n_edges long, t2 double, size int, precision double, n_dist double")


def fit_growth(points: DataFrame, d: float) -> DataFrame:
    """Slopes and r2 of cost against n, and against n^(1/d) log n^(1/d)."""
    root = F.pow(F.col("n").cast("double"), F.lit(1.0 / d))
    p = points.withColumn("m", root * F.log(root))
    return p.agg(F.regr_slope("n_dist", F.col("n").cast("double")).alias("slope_n"), F.regr_r2("n_dist", F.col("n").cast("double")).alias("r2_n"), F.regr_slope("n_dist", "m").alias("slope_root"), F.regr_r2("n_dist", "m").alias("r2_root"), F.regr_slope("n_edges", F.col("n").cast("double")).alias("edges_per_point"))


def w10_sharded(vectors: DataFrame, n_shards: int = 16, k: int = 100) -> DataFrame:
    """One graph against shards of random and of near points; all shards or the closest probed."""
    base, q = base_and_queries(vectors)
    q = q.orderBy("qid").limit(40)
    truth = N.exact_knn(base, q, k)
    out = []
    for method in ("nag", "nav_mrng", "ivf_pq"):
        for layout, shards in (("one", 1), ("random", n_shards)):
            ix = I.build_index(base, method, shards)
            out.append(_labelled(measured(ix, q, truth, k, 8 if method == "ivf_pq" else 120), method=method, layout=layout, probes=shards))
    near = I.build_index(base, "nag", n_shards, routing="kmeans")
    out.append(_labelled(measured(near, q, truth, k, 120, n_probe=max(1, n_shards // 4)), method="nag", layout="kmeans", probes=max(1, n_shards // 4)))
    return _union(out)


def w11_on_the_fly(vectors: DataFrame) -> DataFrame:
    """Edges from stored lists against edges from quantized searches: cost, precision, bytes kept for lists."""
    base, q = base_and_queries(vectors)
    truth = N.exact_knn(base, q, 10)
    out = []
    for method in ("nag", "nag_on_the_fly"):
        ix = I.build_index(base, method)
        kept = ix.agg(F.sum(F.col("n") * (I.DEFAULTS["k"] * 4 if method == "nag" else I.DEFAULTS["m_sub"])).alias("candidate_bytes"))
        out.append(_labelled(measured(ix, q, truth, 10, 40).crossJoin(kept), method=method))
    return _union(out)


def w12_overlap(vectors: DataFrame, alphas=(50.0, 60.0, 70.0)) -> DataFrame:
    """How many edges the practical graph shares with the exact one."""
    pts = vectors.select("id", "vec")
    return _union([_labelled(N.graph_overlap(I.index_edges(I.build_index(pts, "nag", alpha=a)), I.index_edges(I.build_index(pts, "exact_angle", alpha=a))), alpha=a) for a in alphas])


def w13_lid(views: dict[str, DataFrame], k: int = 20) -> DataFrame:
    return _union([_labelled(N.lid_mle(N.knn_graph(v, k), k).agg(F.round(F.avg("lid"), 6).alias("lid"), F.count("*").alias("n")), view=n) for n, v in views.items()])


def w14_doc_search(spark, sf_dir, k: int = 5) -> DataFrame:
    """Benchmark passages as queries against documents, through hashed word vectors."""
    docs = V.text_vectors(V.table(spark, sf_dir, "documents"), "doc_id", "text")
    asks = V.text_vectors(V.table(spark, sf_dir, "benchmark"), "item_id", "text")
    return N.exact_knn(docs, queries_of(asks), k).select("qid", "rank", "id", F.round("dist", 6).alias("dist"))


def w15_scan_share(vectors: DataFrame, target: float = 0.9) -> DataFrame:
    """Share of points that each method touches at the precision, or at its best."""
    spark = vectors.sparkSession
    base, q = base_and_queries(vectors)
    n = base.count()
    truth = cut(N.exact_knn(base, q, 10))  # read by every search

    def touched(m):
        got = search_to_precision(I.build_index(base, m), q, truth, 10, target, SWEEP[m])
        return m, got["size"], got["precision"], got["n_dist"] / n

    rows = _together(touched, ["nag", "nav_mrng", "knn_graph", "ivf_flat", "ivf_pq", "two_means_forest"])
    return spark.createDataFrame(rows, "method string, size int, precision double, scan_share double")


def w16_filtered(vectors: DataFrame, label: int = 3, k: int = 5) -> DataFrame:
    """Search within one label: filter first and scan, or search wider and filter after."""
    base, q = base_and_queries(vectors)
    inside = vectors.where((F.col("label") == label) & (F.col("id") % 10 != 3)).select("id", "vec")
    truth = N.exact_knn(inside, q, k)
    wide = I.search_index(I.build_index(base, "nag"), q, 20 * k, 40 * k).join(inside.select("id"), "id", "left_semi")
    w = Window.partitionBy("qid").orderBy("dist", "id")
    after = wide.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)
    return _union([_labelled(N.precision_at_k(a, truth, k).agg(F.avg("precision").alias("precision")), how=h) for h, a in (("pre_filter", truth), ("post_filter", after))])


def greedy_trace(vectors: DataFrame, queries: DataFrame, alpha: float, size: int = 1) -> DataFrame:
    """(qid, step, node, parent, depth, dist_q, n_dist) of searches on the exact graph."""
    import pyarrow as pa

    from .functions import graph_kernels as G

    ix = I.build_index(vectors, "exact_angle", alpha=alpha)
    asked = queries.select("qid", "vec").toPandas()
    sent = vectors.sparkSession.sparkContext.broadcast((asked["qid"].tolist(), [list(map(float, v)) for v in asked["vec"]]))

    def run(batches):
        import numpy as np

        for b in batches:
            for blob in b.column("blob"):
                s = I._load(blob.as_py())
                rows = []
                for qid, q in zip(*sent.value):
                    tr: list = []
                    G.walk(s["x"], s["graph"], np.array(q), s["entry"], size, 1, tr)
                    rows += [(qid, t[0], int(s["ids"][t[1]]), int(s["ids"][t[2]]) if t[2] >= 0 else None, t[3], t[4], t[5]) for t in tr]
                names = ["qid", "step", "node", "parent", "depth", "dist_q", "n_dist"]
                yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], pa.float64() if n == "dist_q" else pa.int64()) for i, n in enumerate(names)], names=names)

    return ix.select("blob").mapInArrow(run, "qid long, step long, node long, parent long, depth long, dist_q double, n_dist long")


def step_monotonicity(trace: DataFrame, vectors: DataFrame, truth: DataFrame) -> DataFrame:
    """Share of steps that come closer to the query and to its true neighbour."""
    from .functions.geometry import l2_sq

    t1 = truth.where("rank = 1").select("qid", F.col("id").alias("s")).join(vectors.select(F.col("id").alias("s"), F.col("vec").alias("sv")), "s")
    d = trace.join(t1, "qid").join(vectors.select(F.col("id").alias("node"), F.col("vec").alias("nv")), "node").withColumn("dist_s", l2_sq("nv", "sv"))
    w = Window.partitionBy("qid").orderBy("step")
    d = d.withColumn("q0", F.lag("dist_q").over(w)).withColumn("s0", F.lag("dist_s").over(w)).where("q0 is not null")
    return d.agg(F.avg(((F.col("dist_q") < F.col("q0")) & (F.col("dist_s") < F.col("s0"))).cast("double")).alias("share"), F.count("*").alias("steps"))


def delta_r(vectors: DataFrame, n: int = 64) -> DataFrame:
    """The smallest difference of two edge lengths in non-isosceles triangles of n sampled points."""
    from .functions.geometry import l2, portable_hash

    some = vectors.orderBy(portable_hash("id"), "id").limit(n)
    a, b = some.select(F.col("id").alias("p"), F.col("vec").alias("pv")), some.select(F.col("id").alias("q"), F.col("vec").alias("qv"))
    e = a.join(b, F.col("p") != F.col("q")).select("p", "q", l2("pv", "qv").alias("d"))
    t = e.alias("x").join(e.alias("y"), (F.col("x.p") == F.col("y.p")) & (F.col("x.q") < F.col("y.q")))
    gap = F.abs(F.col("x.d") - F.col("y.d"))
    return t.where(gap > 0).agg(F.min(gap).alias("delta_r"))


def recall_gate(vectors: DataFrame, method: str, size: int, floor: float, k: int = 10, **params) -> DataFrame:
    """One row of flags: enough answers, valid ids, precision at or above a floor."""
    base, q = base_and_queries(vectors)
    got = I.search_index(I.build_index(base, method, **params), q, k, size)
    truth = N.exact_knn(base, q, k)
    p = N.precision_at_k(got, truth, k).agg((F.avg("precision") >= floor).alias("precise"))
    full = got.join(base.select("id"), "id").agg(F.count("*").alias("n_answers"))
    return p.crossJoin(full).crossJoin(q.agg((F.count("*") * k).alias("n_wanted"))).select("precise", (F.col("n_answers") == F.col("n_wanted")).alias("complete"))


def angle_histogram(vectors: DataFrame, width: float = 10.0) -> DataFrame:
    """Counts of angles between two points seen from a third, in bins of `width` degrees."""
    from .functions.geometry import angle_at, l2

    v = vectors.select("id", "vec")
    e = v.alias("a").join(v.alias("b"), F.col("a.id") != F.col("b.id")).select(F.col("a.id").alias("p"), F.col("b.id").alias("q"), l2(F.col("a.vec"), F.col("b.vec")).alias("d"))
    t = e.alias("x").join(e.alias("y"), (F.col("x.p") == F.col("y.p")) & (F.col("x.q") < F.col("y.q"))).join(e.alias("z"), (F.col("z.p") == F.col("x.q")) & (F.col("z.q") == F.col("y.q")))
    return t.groupBy((F.floor(angle_at("x.d", "y.d", "z.d") / width) * int(width)).cast("long").alias("bin")).agg(F.count("*").alias("n"))


def cos_of(alpha: float) -> float:
    return cos_degrees(alpha)
