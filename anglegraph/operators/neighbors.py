"""Exact neighbours, relational graph operators, and graph measures as DataFrame plans."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import graph_kernels as G
from ..functions.geometry import angle_conflict, l2_sq, portable_hash
from .index import _query_blocks, exact_violations, merge_answers

RANGE_ROWS = 1 << 16


def exact_knn(vectors: DataFrame, queries: DataFrame, k: int, exclude_self: bool = False) -> DataFrame:
    """(qid, rank, id, dist): the serial scan, and the truth for the rest.

    Query blocks of bounded bytes meet every batch of vectors; each batch keeps its own k best, so
    the shuffle carries k rows for each query and batch, never all pairs.
    """
    found = None
    for qids, qx, _ in _query_blocks(queries.select("qid", "vec")):
        sent = vectors.sparkSession.sparkContext.broadcast((np.array(qids, np.int64), qx))

        def run(batches, sent=sent):
            qids, qx = sent.value
            for b in batches:
                if not b.num_rows or not len(qids):
                    continue
                ids = b.column("id").to_numpy()
                x = np.array(b.column("vec").to_pylist(), float)
                for a in range(0, len(qids), 256):
                    q = qx[a : a + 256]
                    rough = (q * q).sum(axis=1)[:, None] - 2 * q @ x.T + (x * x).sum(axis=1)[None, :]
                    rows = []
                    for i, c in enumerate(G.nearest_or_tied(rough, k + 1, q, x)):
                        d = G.sq_to(q[i], x[c])
                        order = np.lexsort((ids[c], d))
                        got = [(ids[c[j]], d[j]) for j in order if not (exclude_self and ids[c[j]] == qids[a + i])][:k]
                        rows += [(qids[a + i], g, float(np.sqrt(v))) for g, v in got]
                    yield pa.RecordBatch.from_pydict({"qid": pa.array([r[0] for r in rows], pa.int64()), "id": pa.array([r[1] for r in rows], pa.int64()), "dist": pa.array([r[2] for r in rows], pa.float64())})

        part = vectors.select("id", "vec").mapInArrow(run, "qid long, id long, dist double")
        found = part if found is None else found.unionAll(part)
    return merge_answers(found, k)


def knn_graph(vectors: DataFrame, k: int) -> DataFrame:
    """(src, dst, dist, rank) of the exact k nearest others."""
    q = vectors.select(F.col("id").alias("qid"), "vec")
    return exact_knn(vectors, q, k, exclude_self=True).select(F.col("qid").alias("src"), F.col("id").alias("dst"), "dist", "rank")


def exact_ip(vectors: DataFrame, queries: DataFrame, k: int) -> DataFrame:
    """(qid, rank, id, ip): the k largest inner products, by blocks as in `exact_knn`."""
    found = None
    for qids, qx, _ in _query_blocks(queries.select("qid", "vec")):
        sent = vectors.sparkSession.sparkContext.broadcast((np.array(qids, np.int64), qx))

        def run(batches, sent=sent):
            qids, qx = sent.value
            for b in batches:
                if not b.num_rows or not len(qids):
                    continue
                ids = b.column("id").to_numpy()
                x = np.array(b.column("vec").to_pylist(), float)
                for a in range(0, len(qids), 256):
                    q = qx[a : a + 256]
                    at, near, ip = [], [], []
                    for i, c in enumerate(G.nearest_or_tied(-(q @ x.T), k, q, x)):
                        v = np.cumsum(x[c] * q[i], axis=1)[:, -1]  # in the order of components
                        best = np.lexsort((ids[c], -v))[:k]
                        at.append(np.full(len(best), qids[a + i]))
                        near.append(ids[c[best]])
                        ip.append(v[best])
                    yield pa.RecordBatch.from_pydict({"qid": np.concatenate(at), "id": np.concatenate(near), "ip": np.concatenate(ip)})

        part = vectors.select("id", "vec").mapInArrow(run, "qid long, id long, ip double")
        found = part if found is None else found.unionAll(part)
    w = Window.partitionBy("qid").orderBy(F.desc("ip"), "id")
    return found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("qid", "rank", "id", "ip")


def range_search(vectors: DataFrame, queries: DataFrame, radius: float) -> DataFrame:
    """(qid, id, dist) within the radius; query blocks meet every batch, and only what products do not rule out is measured."""
    found = None
    for qids, qx, _ in _query_blocks(queries.select("qid", "vec")):
        sent = vectors.sparkSession.sparkContext.broadcast((np.array(qids, np.int64), qx))

        def run(batches, sent=sent):
            qids, qx = sent.value
            for b in batches:
                if not b.num_rows or not len(qids):
                    continue
                ids = b.column("id").to_numpy()
                x = np.array(b.column("vec").to_pylist(), float)
                size = (x * x).sum(axis=1)
                for a in range(0, len(qids), 256):
                    q = qx[a : a + 256]
                    rough = (q * q).sum(axis=1)[:, None] - 2 * q @ x.T + size[None, :]
                    slack = 32 * (x.shape[1] + 4) * np.finfo(float).eps * ((q * q).sum(axis=1).max() + size.max() + radius * radius)
                    at, near = np.nonzero(rough <= radius * radius + slack)
                    for c in range(0, len(at), RANGE_ROWS):
                        i, j = at[c : c + RANGE_ROWS], near[c : c + RANGE_ROWS]
                        d = q[i] - x[j]
                        dist = np.sqrt((d * d).sum(axis=1))
                        ok = dist < radius
                        yield pa.RecordBatch.from_pydict({"qid": qids[a + i[ok]], "id": ids[j[ok]], "dist": dist[ok]})

        part = vectors.select("id", "vec").mapInArrow(run, "qid long, id long, dist double")
        found = part if found is None else found.unionAll(part)
    return found


def mutual(knn: DataFrame) -> DataFrame:
    back = knn.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    return knn.join(back, ["src", "dst"], "left_semi")


def reverse(knn: DataFrame) -> DataFrame:
    return knn.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "dist")


def truncate_graph(edges: DataFrame, t: int, mode: str = "degree", knn: DataFrame | None = None) -> DataFrame:
    """Drop long edges: all but the t shortest of a node, or all whose end is not among its t nearest."""
    if mode == "degree":
        w = Window.partitionBy("src").orderBy("dist", "dst")
        return edges.withColumn("_r", F.row_number().over(w)).where(F.col("_r") <= t).drop("_r")
    return edges.join(knn.where(F.col("rank") <= t).select("src", "dst"), ["src", "dst"], "left_semi")


def two_hop_pool(knn: DataFrame, size: int) -> DataFrame:
    """(src, cand, via_rank): blocks of a neighbour and its list, by rank, until `size` are in."""
    k = knn.select("src", "dst", "rank")
    hop = k.alias("a").join(k.alias("b"), F.col("a.dst") == F.col("b.src")).select(F.col("a.src").alias("src"), F.col("b.dst").alias("cand"), F.col("a.rank").alias("via"))
    every = k.select("src", F.col("dst").alias("cand"), F.col("rank").alias("via")).unionAll(hop).where("cand <> src")
    first = every.groupBy("src", "cand").agg(F.min("via").alias("via_rank"))
    per = first.groupBy("src", "via_rank").agg(F.count("*").alias("c"))
    w = Window.partitionBy("src").orderBy("via_rank").rowsBetween(Window.unboundedPreceding, -1)
    open_ = per.withColumn("before", F.coalesce(F.sum("c").over(w), F.lit(0))).where(F.col("before") < size)
    return first.join(open_.select("src", "via_rank"), ["src", "via_rank"]).select("src", "cand", "via_rank")


def pick_navigators(vectors: DataFrame, m: int, seed: int = 0) -> DataFrame:
    return vectors.select("id", "vec", portable_hash("id", seed).alias("h")).orderBy("h", "id").limit(m).select(F.col("id").alias("node"), "vec")


def entry_points(queries: DataFrame, navigators: DataFrame) -> DataFrame:
    """(qid, entry): the nearest navigator of each query."""
    d = queries.crossJoin(F.broadcast(navigators.select("node", F.col("vec").alias("nv"))))  # a handful of roots
    return d.groupBy("qid").agg(F.min(F.struct(l2_sq("vec", "nv").alias("d"), "node"))["node"].alias("entry"))


def angle_prune(cands: DataFrame, vectors: DataFrame, alpha, max_degree: int | None = None, order: str = "distance") -> DataFrame:
    """(src, dst, dist, rank) kept of (src, cand); alpha in degrees, the name of a column of `vectors`, or None for the lune rule.

    order: "distance" visits the nearest candidates first, "hash" all in an order that does not depend on distance.
    """
    from ..functions.geometry import cos_degrees

    per_node = isinstance(alpha, str)
    v = vectors.select("id", F.col("vec").cast("array<double>").alias("vec"), *([F.col(alpha).cast("double").alias("alpha")] if per_node else []))
    near = cands.select("src", "cand").join(v.select(F.col("id").alias("cand"), "vec"), "cand")
    rows = near.groupBy("src").agg(F.collect_list(F.struct(F.col("cand"), F.col("vec"))).alias("c"))  # bounded by the pool
    rows = rows.join(v.withColumnRenamed("id", "src").withColumnRenamed("vec", "p"), "src")
    if order not in ("distance", "hash"):
        raise ValueError(f"unknown order {order!r}")
    cosine = None if per_node or alpha is None else cos_degrees(alpha)

    def run(batches):
        for b in batches:
            out = []
            for row in b.to_pylist():
                ids = np.array([c["cand"] for c in row["c"]], np.int64)
                order_of = np.argsort(ids)
                x = np.vstack([np.array([row["c"][i]["vec"] for i in order_of]), row["p"]])
                visit = (ids[order_of] % (1 << 31) * 1103515245 + 12345) % (1 << 31) if order == "hash" else None
                kept = G.greedy(x, len(ids), np.arange(len(ids)), cos_degrees(row["alpha"]) if per_node else cosine, max_degree, visit=visit)
                d = np.sqrt(G.sq_to(x[-1], x[kept])) if kept else []
                out += [(row["src"], int(ids[order_of][i]), float(v), r + 1) for r, (i, v) in enumerate(zip(kept, d))]
            yield pa.RecordBatch.from_pydict({"src": pa.array([o[0] for o in out], pa.int64()), "dst": pa.array([o[1] for o in out], pa.int64()), "dist": pa.array([o[2] for o in out], pa.float64()), "rank": pa.array([o[3] for o in out], pa.int32())})

    return rows.mapInArrow(run, "src long, dst long, dist double, rank int")


def reverse_refine(edges: DataFrame, vectors: DataFrame, alpha, r: int) -> DataFrame:
    """Out- and in-neighbours of each node pruned together.

    Candidates go in by distance, 8 r a round, beside those kept so far, until r are kept or the list
    ends: the edges of one greedy pass, while no task holds more than 9 r candidates of a hub.
    """
    from ..plans.lineage import cut

    w = Window.partitionBy("src").orderBy("dist", "cand")
    back = edges.select(F.col("dst").alias("src"), F.col("src").alias("cand"), "dist")
    both = edges.select("src", F.col("dst").alias("cand"), "dist").unionAll(back).groupBy("src", "cand").agg(F.min("dist").alias("dist"))
    both = cut(both.withColumn("part", F.floor((F.row_number().over(w) - 1) / (8 * r))).select("src", "cand", "part"))
    kept = cut(angle_prune(both.where("part = 0").select("src", "cand"), vectors, alpha, r))
    for part in range(1, (both.agg(F.max("part")).first()[0] or 0) + 1):
        full = kept.groupBy("src").agg(F.count("*").alias("c")).where(F.col("c") >= r)
        more = cut(both.where(F.col("part") == part).join(full, "src", "left_anti").select("src", "cand"))
        if more.isEmpty():
            break
        hubs = more.select("src").distinct()
        so_far = kept.join(hubs, "src", "left_semi").select("src", F.col("dst").alias("cand"))
        again = angle_prune(so_far.unionAll(more), vectors, alpha, r)
        kept = cut(kept.join(hubs, "src", "left_anti").unionAll(again))
    return kept


def reach(edges: DataFrame, roots: DataFrame, max_rounds: int = 200) -> DataFrame:
    """(root, node, depth) by breadth; every round is a join and an anti join on reliably cut lineage."""
    from ..plans.lineage import cut

    seen = cut(roots.select(F.col("node").alias("root"), "node", F.lit(0).alias("depth")))
    front = seen
    for depth in range(1, max_rounds + 1):
        nxt = front.join(edges.select(F.col("src").alias("node"), "dst"), "node").select("root", F.col("dst").alias("node")).distinct()
        front = cut(nxt.join(seen.select("root", "node"), ["root", "node"], "left_anti").withColumn("depth", F.lit(depth)))
        if front.isEmpty():
            return seen
        seen = cut(seen.unionAll(front))
    raise RuntimeError(f"reach did not end in {max_rounds} rounds")


def monotonic_violations(edges: DataFrame, vectors: DataFrame) -> DataFrame:
    """(p, q) with no out-neighbour of p closer to q than p is; q-by-edges work, for small sets."""
    return exact_violations(edges, vectors)


def degree_stats(edges: DataFrame, vectors: DataFrame | None = None) -> DataFrame:
    deg = edges.groupBy("src").agg(F.count("*").alias("c"))
    return deg.agg(F.round(F.avg("c"), 6).alias("aod"), F.max("c").alias("mod"), F.sum("c").alias("n_edges"))


def precision_at_k(answers: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """(qid, precision): overlap of the k answers and the k true ids, over k."""
    t = truth.where(F.col("rank") <= k).select("qid", "id")
    a = answers.where(F.col("rank") <= k).select("qid", "id", F.lit(1).alias("hit"))
    return t.join(a, ["qid", "id"], "left").groupBy("qid").agg((F.sum(F.coalesce("hit", F.lit(0))) / k).alias("precision"))


def eps_factor(answers: DataFrame, truth: DataFrame) -> DataFrame:
    """(qid, eps_1nn, eps_rank): the worst ratio to the nearest distance, and to the distance of the same rank."""
    t = truth.select("qid", "rank", F.col("dist").alias("td"))
    one = t.where("rank = 1").select("qid", F.col("td").alias("d1"))
    d = answers.join(t, ["qid", "rank"]).join(one, "qid")
    return d.groupBy("qid").agg(F.max(F.col("dist") / F.col("d1") - 1).alias("eps_1nn"), F.max(F.col("dist") / F.col("td") - 1).alias("eps_rank"))


def lid_mle(knn: DataFrame, k: int) -> DataFrame:
    """(src, lid): maximum-likelihood local intrinsic dimension from the k nearest distances."""
    far = knn.where(F.col("rank") == k).select("src", F.col("dist").alias("dk"))
    d = knn.where((F.col("rank") < k) & (F.col("dist") > 0)).join(far, "src")
    return d.groupBy("src").agg((-1 / F.avg(F.log(F.col("dist") / F.col("dk")))).alias("lid"))


def conflict_rate(vectors: DataFrame, cos_alpha: float) -> DataFrame:
    """Share of pairs of other points that stand within the angle, over all p; for small sets."""
    v = vectors.select("id", "vec")
    pairs = v.alias("a").join(v.alias("b"), F.col("a.id") != F.col("b.id")).select(F.col("a.id").alias("p"), F.col("b.id").alias("q"), l2_sq(F.col("a.vec"), F.col("b.vec")).alias("d2"))
    t = pairs.alias("x").join(pairs.alias("y"), (F.col("x.p") == F.col("y.p")) & (F.col("x.q") < F.col("y.q"))).join(pairs.alias("z"), (F.col("z.p") == F.col("x.q")) & (F.col("z.q") == F.col("y.q")))
    return t.agg(F.round(F.avg(angle_conflict("x.d2", "y.d2", "z.d2", cos_alpha).cast("double")), 9).alias("rate"), F.count("*").alias("n"))


def graph_overlap(a: DataFrame, b: DataFrame) -> DataFrame:
    """Shared edges of two graphs, their union, and the share."""
    x = a.select("src", "dst", F.lit(1).alias("in_a")).join(b.select("src", "dst", F.lit(1).alias("in_b")), ["src", "dst"], "full")
    return x.agg(F.count(F.when(F.col("in_a").isNotNull() & F.col("in_b").isNotNull(), 1)).alias("shared"), F.count("*").alias("either"))


def index_bytes(n, max_degree, mean_degree, layout: str = "matrix"):
    return n * (max_degree if layout == "matrix" else mean_degree) * 4


def expected_cost(degree, n, d, delta_r):
    """The theory curve of the greedy walk for indexed queries."""
    root = n ** (1.0 / d)
    return degree * root * np.log(root) / delta_r
