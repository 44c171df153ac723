"""One interface to every method: an index is a table of shard blobs, an answer a table of rows.

`build_index` deals vectors to shards and builds each shard's structure in one task; a shard's ids
inside are 32-bit positions, mapped to row ids in the blob. `search_index` sends the queries (behind
a size check, in blocks beyond it) to every shard and merges the shards' answers by a top-k window,
which Spark limits in each task before the shuffle. Shard size is chosen from the row count so that
a task holds SHARD_ROWS points or fewer; `routing` keeps points that are near each other together
and lets a query probe only the closest shards.
"""

from __future__ import annotations

import threading
import time
from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import graph_kernels as G
from ..functions.geometry import cos_degrees, portable_hash
from ..plans.lineage import cut

SHARD_ROWS = 1 << 20
QUERY_BYTES = 256 << 20
SPLIT_QUERIES = 256  # from so many on, queries are dealt to tasks where there are few shards
SENT_BYTES = 256 << 20  # of shards that each worker may hold for that
GRAPHS = ("nag", "nag_on_the_fly", "exact_angle", "mrng", "nav_mrng", "hnsw", "nsw", "knn_graph", "knn_graph_tree", "knn_graph_lsh", "pruned_knn", "diversified")
OTHERS = ("scan", "ivf_flat", "ivf_pq", "pq", "kd_forest", "kmeans_tree", "kd_kmeans_forest", "two_means_forest", "lsh", "spectral_hash")
METHODS = GRAPHS + OTHERS
LISTED = ("nag", "nav_mrng", "knn_graph", "knn_graph_tree", "knn_graph_lsh", "pruned_knn", "diversified")  # built from neighbour lists
REVERSED = ("nag", "nag_on_the_fly", "nav_mrng", "pruned_knn")
SPREAD_ROWS = 4096  # from so many points on, neighbour lists become graphs in many tasks

DEFAULTS = {
    "k": 20, "l": 60, "r": 32, "alpha": 60.0, "n_navigators": 10, "reverse": "reprune", "pool_trim": False, "knn": "exact",
    "m": 12, "ef": 60, "nlists": 16, "m_sub": 8, "bits": 6, "nprobe": 4, "n_trees": 4, "leaf": 24, "branching": 8, "hash_bits": 64, "seed": 0,
}


def _ivf_parts(x, p):
    cells = G.lloyd(x, p["nlists"], seed=p["seed"])
    at = G.assign(x, cells)
    d = x.shape[1]
    m = max(1, min(p["m_sub"], d))
    bounds = np.linspace(0, d, m + 1).astype(int)
    rest = x - cells[at]
    books = [G.lloyd(rest[:, a:b], 1 << p["bits"], seed=p["seed"] + 1 + i) for i, (a, b) in enumerate(zip(bounds, bounds[1:]))]
    codes = np.stack([G.assign(rest[:, a:b], c) for c, a, b in zip(books, bounds, bounds[1:])], axis=1).astype(np.uint8)
    return {"cells": cells, "at": at, "bounds": bounds, "books": books, "codes": codes}


def _adc(s, q, cells) -> tuple[np.ndarray, np.ndarray]:
    """Members of the cells and their quantized squared distances from q."""
    out, dist = [], []
    for c in cells:
        mine = np.flatnonzero(s["at"] == c)
        if len(mine):
            rest = q - s["cells"][c]
            table = [G.sq_to(rest[a:b], book) for book, a, b in zip(s["books"], s["bounds"], s["bounds"][1:])]
            dist.append(sum(t[s["codes"][mine, i]] for i, t in enumerate(table)))
            out.append(mine)
    return (np.concatenate(out), np.concatenate(dist)) if out else (np.zeros(0, int), np.zeros(0))


def _kd(x, at, leaf, rng):
    if len(at) <= leaf:
        return at
    top = np.argsort(-x[at].var(axis=0))[:5]
    dim = int(rng.choice(top))
    cut = float(x[at, dim].mean())
    left = x[at, dim] <= cut
    if left.all() or not left.any():
        return at
    return (dim, cut, _kd(x, at[left], leaf, rng), _kd(x, at[~left], leaf, rng))


def _centers(x, at, leaf, b, rng):
    if len(at) <= leaf:
        return at
    c = G.lloyd(x[at], b, rounds=4, seed=int(rng.integers(1 << 31)))
    side = G.assign(x[at], c)
    if len(np.unique(side)) < 2:
        return at
    return (c, [_centers(x, at[side == j], leaf, b, rng) for j in range(len(c))])


def _leaves(trees, q, checks):
    """Points of the best leaves over all trees, best bin first, and the distances spent on the way."""
    import heapq

    todo, found, spent, tick = [(0.0, i, t) for i, t in enumerate(trees)], [], 0, len(trees)
    heapq.heapify(todo)
    while todo and len(found) < checks:
        bound, _, node = heapq.heappop(todo)
        while not isinstance(node, np.ndarray):
            if len(node) == 4:
                dim, cut, a, b = node
                gap = q[dim] - cut
                near, far = (a, b) if gap <= 0 else (b, a)
                heapq.heappush(todo, (bound + gap * gap, tick, far))
                node = near
            else:
                d = G.sq_to(q, node[0])
                spent += len(d)
                order = np.argsort(d)
                for j in order[1:]:
                    heapq.heappush(todo, (bound + float(d[j] - d[order[0]]), tick, node[1][j]))
                    tick += 1
                node = node[1][order[0]]
            tick += 1
        found.extend(node.tolist())
    return np.unique(np.array(found, int)), spent


def _bucket(s, x) -> np.ndarray:
    """The sign code of points as a number of a few bits."""
    return ((x - s["mean"]) @ s["plane"] > 0) @ (1 << np.arange(s["plane"].shape[1]))


def build_shard(method: str, ids: np.ndarray, x: np.ndarray, p: dict, graph: list | None = None) -> dict:
    """The structure of one shard with its report: seconds for lists (t1) and edges (t2), edges, links.

    graph: the graph by position before its parts are linked, where it is at hand.
    """
    order = np.argsort(ids)
    ids, x = ids[order], np.ascontiguousarray(x[order], dtype=float)
    n = len(ids)
    cos = cos_degrees(p["alpha"])
    s = {"method": method, "ids": ids, "x": x, "p": p, "links": 0, "entry": np.zeros(1, int)}
    t = time.perf_counter()
    lists = None
    if method in LISTED and graph is None:
        lists = G.nn_descent(x, ids, p["k"], seed=p["seed"]) if p["knn"] == "nn_descent" else G.exact_lists(x, p["k"])
    s["t1"] = time.perf_counter() - t
    t = time.perf_counter()
    if method in LISTED or method == "nag_on_the_fly":
        if graph is None:
            if method == "nag_on_the_fly":
                ivf = _ivf_parts(x, p)

                def pool(i):
                    got, d = _adc(ivf, x[i], np.argsort(G.sq_to(x[i], ivf["cells"]))[: p["nprobe"]])
                    got, d = got[got != i], d[got != i]
                    return got[np.lexsort((got, d))][: p["l"]]

                graph = [G.greedy(x, i, c, cos, p["r"]) if len(c) else [] for i, c in enumerate(map(pool, range(n)))]
            else:
                forward = _forward(method, x, lists, p)
                graph = [forward(i) for i in range(n)]
            graph = _refined(method, x, graph, p)
        s["entry"] = np.array([_middle(x)]) if method == "nav_mrng" else G.pick(ids, min(n, p["n_navigators"]), p["seed"])
        if method in REVERSED:
            s["links"] = G.strengthen(x, graph, s["entry"], p["r"])
        if method == "knn_graph_tree":
            s["trees"] = [_kd(x, np.arange(n), p["leaf"], np.random.default_rng(p["seed"]))]
        if method == "knn_graph_lsh":
            s |= {"mean": x.mean(axis=0), "plane": np.random.default_rng(p["seed"]).standard_normal((x.shape[1], min(p["hash_bits"], 12)))}
            code = _bucket(s, x)
            order = np.argsort(code, kind="stable")
            s |= {"members": order, "codes_sorted": code[order]}
        s["graph"] = graph
    elif method in ("exact_angle", "mrng"):
        s["graph"] = G.complete_graph(x, cos if method == "exact_angle" else None) if graph is None else graph
        s["entry"] = G.pick(ids, 1, p["seed"])
    elif method in ("hnsw", "nsw"):
        layers, entry = G.hnsw(x, ids, p["m"], p["ef"], method == "nsw")
        s["graph"], s["upper"], s["entry"] = layers[0], layers[1:], np.array([entry])
    elif method in ("ivf_flat", "ivf_pq", "pq"):
        s |= _ivf_parts(x, p | ({"nlists": 1} if method == "pq" else {}))
    elif method in ("kd_forest", "kmeans_tree", "kd_kmeans_forest", "two_means_forest"):
        rng = np.random.default_rng(p["seed"])
        every = np.arange(n)
        kinds = {
            "kd_forest": lambda: [_kd(x, every, p["leaf"], rng) for _ in range(p["n_trees"])],
            "kmeans_tree": lambda: [_centers(x, every, p["leaf"], p["branching"], rng)],
            "two_means_forest": lambda: [_centers(x, every, p["leaf"], 2, rng) for _ in range(p["n_trees"])],
        }
        if method != "kd_kmeans_forest":
            s["trees"] = kinds[method]()
        else:  # the kind that needs fewer distances for the nearest neighbour of a sample
            probe = G.pick(ids, min(n, 32), p["seed"] + 1)

            def cost(trees):
                total = 0
                for i in probe:
                    d = G.sq_to(x[i], x)
                    d[i] = np.inf
                    for checks in (2 * p["leaf"], 8 * p["leaf"], n):
                        got, spent = _leaves(trees, x[i], checks)
                        if int(d.argmin()) in got:
                            break
                    total += len(got) + spent
                return total

            s["trees"] = min((kinds["kd_forest"](), kinds["kmeans_tree"]()), key=cost)
    elif method in ("lsh", "spectral_hash"):
        rng = np.random.default_rng(p["seed"])
        mean = x.mean(axis=0)
        if method == "lsh":
            plane = rng.standard_normal((x.shape[1], p["hash_bits"]))
        else:
            _, _, v = np.linalg.svd(x - mean, full_matrices=False)
            plane = v[: p["hash_bits"]].T
        s |= {"mean": mean, "plane": plane, "signs": np.packbits((x - mean) @ plane > 0, axis=1)}
    elif method != "scan":
        raise ValueError(f"unknown method {method}")
    if "graph" in s:
        s["graph"] = G.Ragged.of(s["graph"])
    s["t2"] = time.perf_counter() - t
    return s


def _middle(x: np.ndarray) -> int:
    return int(G.sq_to(x.mean(axis=0), x).argmin())


def _forward(method: str, x: np.ndarray, lists: np.ndarray, p: dict):
    """The out-neighbours of a point before any reverse step, as a function of its position."""
    cos = cos_degrees(p["alpha"]) if method == "nag" else None
    if method in ("nag", "pruned_knn"):  # pruned_knn: neighbour lists thinned by the lune rule, with back edges

        def out(i):
            c = G.two_hop(lists, i, p["l"], x if p["pool_trim"] else None) if method == "nag" else lists[i]
            return G.greedy(x, i, c, cos, p["r"]) if len(c) else []

    elif method == "nav_mrng":
        mid, rows = _middle(x), G.Ragged(np.full(len(lists), lists.shape[1]), lists.ravel())

        def out(i):
            tr: list = []
            found, *_ = G.walk(x, rows, x[i], [mid], p["l"], p["l"], tr)
            pool = np.unique(np.array(found + [e[1] for e in tr] + rows[i], int))
            return G.greedy(x, i, pool[pool != i], None, p["r"])

    elif method == "diversified":

        def out(i):
            return G.widest(x, i, lists[i], max(1, len(lists[i]) // 2)) if len(lists[i]) else []

    else:

        def out(i):
            return lists[i].tolist()

    return out


def _reverse(method: str, x: np.ndarray, p: dict):
    """The out-neighbours after the reverse step, as a function of a position, its out-neighbours and those it is one of."""
    if method in REVERSED:
        cos = cos_degrees(p["alpha"]) if method in ("nag", "nag_on_the_fly") else None
        mode = p["reverse"] if method in ("nag", "nag_on_the_fly") else "insert"
        return lambda q, out, incoming: G.refined(x, q, out, incoming, cos, p["r"], mode)
    if method == "diversified":
        return lambda q, out, incoming: out + [i for i in incoming if i not in set(out)]
    return lambda q, out, incoming: out


def _refined(method: str, x: np.ndarray, graph: list, p: dict) -> list:
    back, step = G.Ragged.of(graph).reversed(), _reverse(method, x, p)
    return [step(q, out, back[q]) for q, out in enumerate(graph)]


def search_shard(s: dict, q: np.ndarray, k: int, size: int):
    """Positions, squared distances, and the numbers of distances, expansions and hops, of one query."""
    x, method = s["x"], s["method"]
    if len(x) == 0:
        return [], [], 0, 0, 0
    if "graph" in s:
        at, spent = s["entry"], 0
        for layer in reversed(s.get("upper", [])):
            found, _, n, *_ = G.walk(x, layer, q, at, 1, 1)
            at, spent = np.array(found), spent + n
        if "trees" in s:
            at, extra = _leaves(s["trees"], q, 1)
            spent += extra
        if "members" in s:  # starts from the query's bucket, where it is not empty
            a, b = (np.searchsorted(s["codes_sorted"], _bucket(s, q), side) for side in ("left", "right"))
            at = s["members"][a : min(b, a + s["p"]["n_navigators"])] if a < b else at
        pos, d, n, e, h = G.walk(x, s["graph"], q, at, max(size, k), k)
        return pos, d, n + spent, e, h
    if method == "scan":
        cand, spent = np.arange(len(x)), 0
    elif method in ("ivf_flat", "ivf_pq", "pq"):
        cells = np.argsort(G.sq_to(q, s["cells"]), kind="stable")[: max(1, size)]
        spent = len(s["cells"])
        cand, d = _adc(s, q, cells)
        if method != "ivf_flat":
            order = np.lexsort((cand, d))[:k]
            return cand[order].tolist(), G.sq_to(q, x[cand[order]]).tolist(), spent + len(cand), 0, 0
    elif "trees" in s:
        cand, spent = _leaves(s["trees"], q, max(size, k))
    else:
        code = np.packbits((q - s["mean"]) @ s["plane"] > 0)
        away = np.bitwise_count(s["signs"] ^ code).sum(axis=1)
        cand, spent = np.argsort(away, kind="stable")[: max(size, k)], 0
    d = G.sq_to(q, x[cand])
    order = np.lexsort((cand, d))[:k]
    return cand[order].tolist(), d[order].tolist(), spent + len(cand), 0, 0


def _dump(s: dict) -> bytes:
    import pickle

    g = s.get("graph")
    return pickle.dumps(s if g is None else s | {"graph": (g.count, g.to)}, protocol=5)


def _load(blob: bytes) -> dict:
    import pickle

    s = pickle.loads(blob)
    return s | {"graph": G.Ragged(*s["graph"])} if "graph" in s else s


def _vectors(rows: pa.Table) -> np.ndarray:
    n = rows.num_rows
    return np.array(rows.column("vec").to_pylist(), float).reshape(n, -1)


def shard_of(vectors: DataFrame, n_shards: int | None, routing: str = "random", seed: int = 0) -> DataFrame:
    """The vectors with `shard`: an even hash of the id, or the nearest of sampled centres."""
    if n_shards is None:
        n_shards = max(1, -(-vectors.count() // SHARD_ROWS))
    if routing == "random":
        return vectors.withColumn("shard", (F.floor(portable_hash("id", seed) / 64) % n_shards).cast("int"))
    if routing != "kmeans":
        raise ValueError("routing is 'random' or 'kmeans'")
    centres = route_centres(vectors, n_shards, seed)

    def deal(batches):
        for b in batches:
            at = G.assign(np.array(b.column("vec").to_pylist(), float).reshape(b.num_rows, -1), centres) if b.num_rows else []
            yield b.append_column("shard", pa.array(at, pa.int32()))

    return vectors.select("id", "vec").mapInArrow(deal, f"id long, vec {vectors.schema['vec'].dataType.simpleString()}, shard int")


def route_centres(vectors: DataFrame, n_shards: int, seed: int = 0, sample: int = 4096) -> np.ndarray:
    """k-means centres of at most `sample` vectors, those with the smallest hashes."""
    some = vectors.orderBy(portable_hash("id", seed), "id").limit(sample).select("vec").toPandas()
    return G.lloyd(np.array(some["vec"].tolist(), float), n_shards, seed=seed)


class _OneThread:
    """Runs work alone of all builds that run at once, and on one thread, as each thread's freed memory stays with it."""

    def __init__(self):
        self.pool = ThreadPoolExecutor(1, "arrays-on-driver")

    def __call__(self, work):
        if threading.current_thread().name.startswith("arrays-on-driver"):
            return work()
        return self.pool.submit(inheritable_thread_target(work)).result()

    def __reduce__(self):
        return _OneThread, ()


on_driver = _OneThread()
EDGE_ROWS = 1 << 18
POINTS_A_TASK = 256


def matrix_of(vectors: DataFrame, columns: dict[str, str] | None = None) -> tuple:
    """(ids, vectors, further columns) as arrays in the order of ids; rows reach the driver packed, not as objects."""
    kinds = columns or {}

    def pack(batches):
        for b in batches:
            if b.num_rows:
                x = _vectors(pa.Table.from_batches([b]))
                yield pa.RecordBatch.from_pydict({"n": pa.array([b.num_rows], pa.int64()), "ids": [b.column("id").to_numpy().astype("<i8").tobytes()], "x": [x.tobytes()], **{c: [b.column(c).to_numpy().astype(k).tobytes()] for c, k in kinds.items()}})

    def collect():
        rows = vectors.select("id", "vec", *kinds).mapInArrow(pack, "n long, ids binary, x binary" + "".join(f", {c} binary" for c in kinds)).toArrow()
        joined = lambda c, kind: np.concatenate([np.frombuffer(v.as_buffer(), kind) for v in rows.column(c)] or [np.zeros(0, kind)])
        ids, x, *more = joined("ids", "<i8"), joined("x", "<f8"), *[joined(c, k) for c, k in kinds.items()]
        del rows, joined
        pa.default_memory_pool().release_unused()
        x = x.reshape(len(ids), -1) if len(ids) else np.zeros((0, 0))
        if not (ids[1:] >= ids[:-1]).all():
            order = np.argsort(ids, kind="stable")
            ids, x, *more = ids[order], x[order], *[m[order] for m in more]
        return ids, x, *more

    return on_driver(collect)


def _dealt(by: np.ndarray, *columns) -> list:
    """The columns in an order, not copied where they have it."""
    return list(columns) if (np.diff(by) == 1).all() else [c[by] for c in columns]


def exact_graph(vectors: DataFrame, alpha, order: str = "distance") -> DataFrame:
    """(src, dst, dist, rank): pruning of all other points, its sources dealt to tasks that share one matrix.

    alpha: degrees, the name of a column of them, or None for the lune rule; order as for `angle_prune`.
    A column `shard` keeps edges inside shards. Time grows with the square of a shard, at least; no pairs are shuffled.
    """
    if order not in ("distance", "hash"):
        raise ValueError(f"unknown order {order!r}")
    named = isinstance(alpha, str)
    v = vectors.withColumn(alpha, F.col(alpha).cast("double")) if named else vectors
    v = v if "shard" in v.columns else v.withColumn("shard", F.lit(0))
    spark = vectors.sparkSession

    def send():
        got = matrix_of(v.withColumn("shard", F.col("shard").cast("long")), {"shard": "<i8"} | ({alpha: "<f8"} if named else {}))
        ids, x, shard = got[:3]
        n, by = len(ids), np.argsort(shard, kind="stable")
        starts = np.flatnonzero(np.diff(shard[by], prepend=np.nan) != 0) if n else []
        cosine = np.array([cos_degrees(a) for a in got[3][by]]) if named else None if alpha is None else cos_degrees(alpha)
        ids, x = _dealt(by, ids, x)
        return n, spark.sparkContext.broadcast((ids, x, [*map(int, starts), n], cosine, {}))

    n, sent = on_driver(send)

    def run(batches):
        ids, x, bounds, cosine, held = sent.value  # what a worker makes of a shard's points stays there
        out, size = [], 0

        def flush():
            src, dst, dist, rank = (np.concatenate(c) for c in zip(*out))
            return pa.RecordBatch.from_arrays([pa.array(src), pa.array(dst), pa.array(dist), pa.array(rank, pa.int32())], names=["src", "dst", "dist", "rank"])

        for b in batches:
            at = b.column("id").to_numpy()
            for lo, hi in zip(bounds, bounds[1:]):
                mine = at[(at >= lo) & (at < hi)] - lo
                if not len(mine):
                    continue
                own = ids[lo:hi]
                visit = (own % (1 << 31) * 1103515245 + 12345) % (1 << 31) if order == "hash" else None
                for p, kept, d2 in G.pruned_rows(x[lo:hi], mine, cosine[lo:hi] if isinstance(cosine, np.ndarray) else cosine, visit, held.setdefault(lo, {})):
                    out.append((np.full(len(kept), own[p]), own[kept], np.sqrt(d2), np.arange(1, len(kept) + 1)))
                    size += len(kept)
                    if size >= EDGE_ROWS:
                        yield flush()
                        out, size = [], 0
        if size:
            yield flush()

    return _sources(spark, n).mapInArrow(run, "src long, dst long, dist double, rank int")


def _sources(spark, n: int) -> DataFrame:
    """The positions of n points, few in each task."""
    tasks = max(spark.sparkContext.defaultParallelism, -(-n // POINTS_A_TASK))
    return spark.range(0, n, 1, min(tasks, 4096))


def exact_alpha_for_degree(vectors: DataFrame, target: int, grid=(30.0, 40.0, 50.0, 60.0)) -> DataFrame:
    """(src, alpha, degree): `alpha_for_degree` with all other points as candidates; an angle is left once its degree can no longer win."""
    spark = vectors.sparkSession
    ids, x = matrix_of(vectors)
    sent = spark.sparkContext.broadcast((ids, x, sorted(((cos_degrees(a), float(a)) for a in grid), key=lambda g: -g[1])))

    def run(batches):
        ids, x, grid = sent.value
        for b in batches:
            at = b.column("id").to_numpy()
            rows = [(int(ids[p]), *best) for p, best in G.degree_rows(x, at, target, grid) if best]
            yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.float64()), pa.array([r[2] for r in rows], pa.int64())], names=["src", "alpha", "degree"])

    return _sources(spark, len(ids)).mapInArrow(run, "src long, alpha double, degree long")


def exact_violations(edges: DataFrame, vectors: DataFrame) -> DataFrame:
    """(p, q) with no out-neighbour of p closer to q than p is; tasks share one matrix, no pairs are shuffled."""
    ids, x = matrix_of(vectors)
    sent = vectors.sparkSession.sparkContext.broadcast((ids, x))
    lists = edges.groupBy("src").agg(F.collect_list("dst").alias("dst"))
    lists = vectors.select(F.col("id").alias("src")).join(lists, "src", "left")

    def run(batches):
        ids, x = sent.value
        for b in batches:
            at = np.searchsorted(ids, b.column("src").to_numpy())
            outs = [np.searchsorted(ids, to.values.to_numpy()) if to.is_valid else np.zeros(0, np.int64) for to in b.column("dst")]
            for p, q in G.unreached_rows(x, at, outs):
                if len(q):
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(q), ids[p])), pa.array(ids[q])], names=["p", "q"])

    return lists.mapInArrow(run, "p long, q long")


def _spread(dealt: DataFrame, method: str, p: dict) -> DataFrame:
    """(part, at, count, dst, t1, t2): the out-neighbours of stretches of a shard's points, made by many tasks that share one matrix.

    Three rounds, for lists, out-neighbours and the reverse step, of the same kernels as for a shard in one task;
    what a round needs of the one before is as long as the graph. t1, t2: seconds of the tasks.
    """
    spark = dealt.sparkSession

    def send():
        ids, x, shard = matrix_of(dealt.withColumn("shard", F.col("shard").cast("long")), {"shard": "<i8"})
        by = np.argsort(shard, kind="stable")
        starts = np.flatnonzero(np.diff(shard[by], prepend=np.nan) != 0).tolist()
        (x,) = _dealt(by, x)
        return starts, [*starts, len(by)], spark.sparkContext.broadcast((x, shard[by][starts].tolist(), [*starts, len(by)]))

    starts, ends, sent = on_driver(send)
    ddl = "part int, lo long, at binary, count binary, dst binary, t1 double, t2 double"
    packed = lambda v: np.asarray(v, "<i4").tobytes()

    def round_of(work, seconds):
        def run(batches):
            x, parts, bounds = sent.value
            for b in batches:
                pos = b.column("id").to_numpy()
                for part, lo, hi in zip(parts, bounds, bounds[1:]):
                    mine = pos[(pos >= lo) & (pos < hi)] - lo
                    if len(mine):
                        began = time.perf_counter()
                        out = G.Ragged.of(work(x[lo:hi], mine, lo, hi))
                        took = {"t1": 0.0, "t2": 0.0, seconds: time.perf_counter() - began}
                        yield pa.RecordBatch.from_pydict({"part": pa.array([part], pa.int32()), "lo": [lo], "at": [packed(mine)], "count": [packed(out.count)], "dst": [packed(out.to)], **{c: [v] for c, v in took.items()}})

        return _sources(spark, ends[-1]).mapInArrow(run, ddl)

    def held(rows: DataFrame):
        """A round's lists by position, those of each shard by positions in it, and the seconds taken in each shard."""
        got = sorted(rows.toArrow().to_pylist(), key=lambda r: r["lo"] + int(np.frombuffer(r["at"][:4], "<i4")[0]))
        took: dict[int, list[float]] = {}
        for r in got:
            took.setdefault(r["part"], []).append((r["t1"], r["t2"]))
        count, to = (np.concatenate([np.frombuffer(r[c], "<i4") for r in got]) for c in ("count", "dst"))
        return G.Ragged(count, to), took

    lists, took1 = held(round_of(lambda x, at, lo, hi: G.exact_lists(x, p["k"], of=at).tolist(), "t1"))
    near = spark.sparkContext.broadcast((lists.count, lists.to, lists.start))

    def forward(x, at, lo, hi):
        count, to, start = near.value
        mine = to[start[lo] : start[hi - 1] + count[hi - 1]].reshape(hi - lo, -1)
        step = _forward(method, x, mine, p)
        return [step(i) for i in at.tolist()]

    graph, took2 = held(round_of(forward, "t2"))
    sides = [G.Ragged(graph.count[a:b], graph.to[graph.start[a] : graph.start[b - 1] + graph.count[b - 1]]) for a, b in zip(ends, ends[1:])]
    both = spark.sparkContext.broadcast({a: (g, g.reversed()) for a, g in zip(starts, sides)})

    def reverse(x, at, lo, hi):
        out, back = both.value[lo]
        step = _reverse(method, x, p)
        return [step(q, out[q], back[q]) for q in at.tolist()]

    done = [(part, b"", b"", b"", *np.array(took1[part] + took2[part]).sum(axis=0).tolist()) for part in took1]
    before = spark.createDataFrame([(int(a), bytearray(b), bytearray(c), bytearray(d), t1, t2) for a, b, c, d, t1, t2 in done], "part int, at binary, count binary, dst binary, t1 double, t2 double")
    return round_of(reverse, "t2").drop("lo").unionByName(before)


def build_index(vectors: DataFrame, method: str, n_shards: int | None = 1, routing: str = "random", **params) -> DataFrame:
    """(shard, method, n, t1, t2, n_edges, max_degree, links, centre, peak_mb, blob): one row for each shard of (id, vec)."""
    if method not in METHODS:
        raise ValueError(f"method is one of {METHODS}")
    unknown = set(params) - set(DEFAULTS)
    if unknown:
        raise ValueError(f"unknown parameters {sorted(unknown)}")
    p = DEFAULTS | params
    dealt = shard_of(vectors.select("id", "vec"), n_shards, routing, p["seed"])

    def build(key: tuple[pa.Scalar, ...], rows: pa.Table) -> pa.Table:
        return report(key, rows, None)

    def assemble(key: tuple[pa.Scalar, ...], rows: pa.Table, out: pa.Table) -> pa.Table:
        own = np.sort(rows.column("id").to_numpy())
        graph: list[list[int]] = [[] for _ in own]
        for at, to in zip(np.searchsorted(own, out.column("src").to_numpy()).tolist(), out.column("dst")):
            graph[at] = np.searchsorted(own, to.values.to_numpy()).tolist()
        return report(key, rows, graph)

    def finish(key: tuple[pa.Scalar, ...], rows: pa.Table, parts: pa.Table) -> pa.Table:
        at, count, to = (np.concatenate([np.frombuffer(v.as_py(), "<i4") for v in parts.column(c)]) for c in ("at", "count", "dst"))
        g = G.Ragged(count, to)
        order = np.argsort(at)
        ends = np.repeat(g.start[order] - np.cumsum(count[order]) + count[order], count[order]) + np.arange(len(to))
        took = [pc.sum(parts.column(c)).as_py() for c in ("t1", "t2")]
        return report(key, rows, G.Ragged(count[order], to[ends]), *took)

    def report(key, rows, graph, t1=0.0, t2=0.0):
        import resource

        s = build_shard(method, rows.column("id").to_numpy(), _vectors(rows), p, graph)
        s["t1"], s["t2"] = s["t1"] + t1, s["t2"] + t2
        deg = [len(g) for g in s.get("graph", [])] or [0]
        blob = _dump(s)
        return pa.table({"shard": pa.array([key[0].as_py()], pa.int32()), "method": [method], "n": pa.array([rows.num_rows], pa.int64()), "t1": [s["t1"]], "t2": [s["t2"]], "n_edges": pa.array([sum(deg)], pa.int64()), "max_degree": pa.array([max(deg)], pa.int64()), "links": pa.array([s["links"]], pa.int64()), "centre": [s["x"].mean(axis=0).tolist()], "peak_mb": [resource.getrusage(resource.RUSAGE_SELF).ru_maxrss / 1024], "blob": pa.array([blob], pa.binary())})

    ddl = "shard int, method string, n long, t1 double, t2 double, n_edges long, max_degree long, links long, centre array<double>, peak_mb double, blob binary"
    if method in LISTED and p["knn"] == "exact":
        dealt = cut(dealt)
        if dealt.count() >= SPREAD_ROWS:
            return cut(dealt.groupBy("shard").cogroup(_spread(dealt, method, p).groupBy("part")).applyInArrow(finish, ddl))
    if method not in ("exact_angle", "mrng"):
        return cut(dealt.groupBy("shard").applyInArrow(build, ddl))  # an index is built once, however many searches follow
    dealt = cut(dealt)
    edges = exact_graph(dealt, p["alpha"] if method == "exact_angle" else None)
    lists = edges.groupBy("src").agg(F.transform(F.array_sort(F.collect_list(F.struct("rank", "dst"))), lambda e: e["dst"]).alias("dst"))
    lists = lists.join(dealt.select(F.col("id").alias("src"), F.col("shard").alias("part")), "src")
    return cut(dealt.groupBy("shard").cogroup(lists.groupBy("part")).applyInArrow(assemble, ddl))


def index_edges(index: DataFrame) -> DataFrame:
    """(src, dst, dist, rank) of the graphs in an index."""

    def run(batches):
        for b in batches:
            for blob in b.column("blob"):
                s = _load(blob.as_py())
                ids, x = s["ids"], s["x"]
                for i, g in enumerate(s.get("graph", [])):
                    if g:
                        d = np.sqrt(G.sq_to(x[i], x[g]))
                        yield pa.RecordBatch.from_pydict({"src": pa.array([ids[i]] * len(g), pa.int64()), "dst": pa.array(ids[g], pa.int64()), "dist": pa.array(d), "rank": pa.array(np.argsort(np.argsort(d, kind="stable")) + 1, pa.int32())})

    return index.select("blob").mapInArrow(run, "src long, dst long, dist double, rank int")


def index_violations(index: DataFrame) -> DataFrame:
    """(violations): pairs without a monotone first step, over the shards; n squared in a shard."""

    def run(batches):
        for b in batches:
            for blob in b.column("blob"):
                s = _load(blob.as_py())
                yield pa.RecordBatch.from_pydict({"v": pa.array([G.violations(s["x"], s["graph"])], pa.int64())})

    return index.select("blob").mapInArrow(run, "v long").agg(F.sum("v").alias("violations"))


ANSWERS = "qid long, id long, dist double, n_dist long, expansions long, hops long"


def search_index(index: DataFrame, queries: DataFrame, k: int, size: int, **more) -> DataFrame:
    """(qid, rank, id, dist): the k nearest found over all shards."""
    return merge_answers(search_shards(index, queries, k, size, **more), k)


def search_shards(index: DataFrame, queries: DataFrame, k: int, size: int, n_probe: int | None = None, exclude_self: bool = False) -> DataFrame:
    """(qid, id, dist, n_dist, expansions, hops): the k nearest that each shard finds.

    queries: (qid, vec). The counts of a shard stand on its first row for a query, so sums over a
    query count each shard once. n_probe: the shards with the closest centres only.
    """
    spark = index.sparkSession
    ask = queries.select("qid", "vec")
    take = k + int(exclude_self)
    probed = None if n_probe is None else index.select("shard", "centre").toPandas()

    def answer(shard, s, block):
        rows = []
        for i, (qid, q) in enumerate(zip(*block[:2])):
            if block[2] is not None and shard not in block[2][i]:
                continue
            pos, d, n, e, h = search_shard(s, q, take, size)
            got = [(int(s["ids"][p]), float(v)) for p, v in zip(pos, d)]
            got = [g for g in got if not (exclude_self and g[0] == qid)][:k]
            rows += [(qid, g, float(np.sqrt(v)), *((n, e, h) if j == 0 else (0, 0, 0))) for j, (g, v) in enumerate(got)]
        return pd.DataFrame(rows, columns=["qid", "id", "dist", "n_dist", "expansions", "hops"]).astype({"qid": "int64", "id": "int64", "dist": "float64", "n_dist": "int64", "expansions": "int64", "hops": "int64"})

    found = None
    for block in _query_blocks(ask):
        if probed is not None:
            c = np.array(probed["centre"].tolist())
            order = np.argsort(((block[1][:, None, :] - c[None]) ** 2).sum(axis=2), axis=1)[:, :n_probe]
            block = (block[0], block[1], [set(probed["shard"].to_numpy()[o].tolist()) for o in order])
        part = each_shard(index, block, answer, ANSWERS)
        found = part if found is None else found.unionAll(part)
    return found


def each_shard(index: DataFrame, block: tuple, work, ddl: str) -> DataFrame:
    """The rows of work(shard number, shard, queries) over all shards and the queries of a block (qids, vectors, shards probed).

    Many queries for few shards of up to SENT_BYTES are dealt to tasks that share the shards; else each shard gets all queries.
    """
    spark, n = index.sparkSession, len(block[0])
    schema = _arrow(ddl)
    if n >= SPLIT_QUERIES:
        size = index.agg(F.count("*").alias("n"), F.sum(F.octet_length("blob")).alias("b")).first()
        if size["n"] < spark.sparkContext.defaultParallelism and size["b"] <= SENT_BYTES:
            def send():
                rows = index.select("shard", "blob").toArrow()
                return spark.sparkContext.broadcast((block, list(zip(rows.column("shard").to_pylist(), rows.column("blob").to_pylist()))))

            both = on_driver(send)

            def dealt(batches):
                block, shards = both.value
                for b in batches:
                    at = b.column("id").to_numpy()
                    if len(at):
                        near = None if block[2] is None else [block[2][i] for i in at]
                        mine = ([block[0][i] for i in at], block[1][at], near)
                        for i, (shard, s) in enumerate(shards):
                            if isinstance(s, bytes):  # unpacked once by a worker
                                shards[i] = shard, s = shard, _load(s)
                            yield pa.RecordBatch.from_pandas(work(shard, s, mine), schema, preserve_index=False)

            tasks = max(4 * spark.sparkContext.defaultParallelism, -(-n // 8192))
            return spark.range(0, n, 1, tasks).mapInArrow(dealt, ddl)
    sent = spark.sparkContext.broadcast(block)

    def run(batches):
        for b in batches:
            for shard, blob in zip(b.column("shard").to_pylist(), b.column("blob")):
                yield pa.RecordBatch.from_pandas(work(shard, _load(blob.as_py()), sent.value), schema, preserve_index=False)

    return index.select("shard", "blob").mapInArrow(run, ddl)


def _arrow(ddl: str) -> pa.Schema:
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import StructType

    return to_arrow_schema(StructType.fromDDL(ddl))


def _query_blocks(ask: DataFrame):
    """The queries in blocks of QUERY_BYTES or less, read one partition at a time."""
    ids, vecs, size = [], [], 0
    for row in ask.toLocalIterator():
        ids.append(row["qid"])
        vecs.append(row["vec"])
        size += 8 * len(row["vec"])
        if size >= QUERY_BYTES:
            yield ids, np.array(vecs, float), None
            ids, vecs, size = [], [], 0
    yield ids, np.array(vecs, float), None


def merge_answers(found: DataFrame, k: int) -> DataFrame:
    """The k best of each query over all shards."""
    w = Window.partitionBy("qid").orderBy("dist", "id")
    best = found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)
    return best.select("qid", "rank", "id", "dist")


def save_index(index: DataFrame, path: str) -> None:
    """One Parquet directory for each shard, so that a load can prune."""
    index.write.mode("overwrite").partitionBy("shard").parquet(path)


def load_index(spark, path: str, shards: list[int] | None = None) -> DataFrame:
    d = spark.read.parquet(path)
    return d if shards is None else d.where(F.col("shard").isin(shards))
