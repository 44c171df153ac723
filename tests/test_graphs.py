import numpy as np
import pytest

from anglegraph import workloads as X
from anglegraph.functions import graph_kernels as G
from anglegraph.functions.geometry import cos_degrees
from anglegraph.operators import index as I
from anglegraph.operators import neighbors as N

# The fan: P, A, B, E, D, C.
FAN = np.array([[0, 0], [1, 0], [0, 2], [1, 1.8], [-1.5, -1.5], [2, 1]], float)
NAMES = "PABEDC"


def kept(points, alpha, names=NAMES):
    cos = None if alpha is None else cos_degrees(alpha)
    return "".join(names[i] for i in G.greedy(points, 0, np.arange(1, len(points)), cos))


@pytest.mark.parametrize("alpha,want", [(60, "ABD"), (30, "ABD"), (28, "ABED"), (20, "ABEDC"), (90, "ABD"), (None, "ABD"), (0, "ABEDC")])
def test_fan(alpha, want):
    assert kept(FAN, alpha) == want


def test_fan_without_b_tells_the_rules_apart():
    pts = np.delete(FAN, 2, axis=0)
    assert kept(pts, 60, "PAEDC") == "AED" and kept(pts, None, "PAEDC") == "AD"


def test_dropped_edges_do_not_block():
    a = np.radians([0, 40, 80])
    pts = np.vstack([[0, 0], np.c_[np.cos(a), np.sin(a)] * [[1], [2], [3]]])
    assert G.greedy(pts, 0, np.array([1, 2, 3]), 0.5) == [1, 3]


def random_points(n, d, seed=1):
    return np.random.default_rng(seed).standard_normal((n, d))


def test_monotone_up_to_60_and_greedy_finds_indexed_points():
    x = random_points(80, 6)
    g = G.complete_graph(x, 0.5)
    assert G.violations(x, g) == 0
    assert all(G.walk(x, g, x[q], [0], 1, 1)[0] == [q] for q in range(len(x)))
    assert G.violations(x, G.complete_graph(x, None)) == 0


def test_pruning_by_pool_matches_plain_loops():
    x = random_points(300, 4)
    cands = np.arange(1, 300)
    d = ((x[cands] - x[0]) ** 2).sum(axis=1)
    out = []
    for c in cands[np.lexsort((cands, d))]:
        v = x[c] - x[0]
        if all(v @ (x[r] - x[0]) / np.linalg.norm(v) / np.linalg.norm(x[r] - x[0]) <= 0.5 for r in out):
            out.append(int(c))
    assert G.greedy(x, 0, cands, 0.5) == out


def test_two_blobs_are_connected():
    x = np.vstack([random_points(30, 2), random_points(30, 2, 2) + [100, 0]])
    g = [r.tolist() for r in G.exact_lists(x, 5)]
    assert not G.reached(g, 0).all()
    assert G.strengthen(x, g, [0, 40], 8) >= 2
    assert G.reached(g, 0).all() and G.reached(g, 40).all()


def test_line_is_the_worst_case():
    x = np.c_[np.arange(20.0), np.zeros(20)]
    g = G.complete_graph(x, 0.5)
    assert [sorted(o) for o in g][1:-1] == [[i - 1, i + 1] for i in range(1, 19)]
    assert G.walk(x, g, x[19], [0], 1, 1)[4] == 19


def test_star_hub_respects_the_cap():
    a = np.linspace(0, 2 * np.pi, 11)[:-1]
    x = np.vstack([[0, 0], np.c_[np.cos(a), np.sin(a)] * np.arange(1, 11)[:, None]])
    g = G.reverse_refine(x, [[]] + [[0]] * 10, 0.5, 3)
    assert len(g[0]) == 3


def test_two_hop_pool_takes_whole_blocks():
    lists = np.array([[1, 2], [3, 0], [4, 5], [1, 2], [5, 2], [4, 2]])
    assert sorted(G.two_hop(lists, 0, 2)) == [1, 3]
    assert sorted(G.two_hop(lists, 0, 3)) == [1, 2, 3, 4, 5]


def vectors(spark, x, ids=None):
    return spark.createDataFrame([(int(i), [float(v) for v in r]) for i, r in zip(ids if ids is not None else range(len(x)), x)], "id long, vec array<double>")


@pytest.mark.parametrize("method", I.METHODS)
def test_every_method_finds_most_neighbours(spark, method):
    x = random_points(160, 4)
    v = vectors(spark, x)
    q = X.queries_of(v.where("id % 8 = 0"))
    size = 16 if method in ("ivf_flat", "ivf_pq", "pq") else 160
    got = I.search_index(I.build_index(v, method), q, 5, size)
    p = N.precision_at_k(got, N.exact_knn(v, q, 5), 5).agg({"precision": "avg"}).first()[0]
    assert p >= (0.5 if method in ("ivf_pq", "pq") else 0.95)


def test_shards_merge_to_the_exact_answer_and_partitioning_changes_nothing(spark):
    v = vectors(spark, random_points(120, 3))
    q = X.queries_of(v.where("id < 10"))
    want = [tuple(r)[:3] for r in N.exact_knn(v, q, 7).orderBy("qid", "rank").collect()]
    for n in (1, 3):
        assert [tuple(r)[:3] for r in I.search_index(I.build_index(v.repartition(n + 1), "scan", n), q, 7, 7).orderBy("qid", "rank").collect()] == want


def test_relational_and_kernel_pools_agree(spark):
    x = random_points(60, 3)
    knn = N.knn_graph(vectors(spark, x), 6)
    lists = G.exact_lists(x, 6)
    rel: dict = {}
    for r in N.two_hop_pool(knn, 15).collect():
        rel.setdefault(r["src"], set()).add(r["cand"])
    assert all(rel[p] == set(G.two_hop(lists, p, 15).tolist()) for p in range(60))


def test_bad_vectors_and_parameters(spark):
    from anglegraph.sources.vectors import validate_vectors

    with pytest.raises(ValueError):
        validate_vectors(spark.createDataFrame([(1, [1.0]), (2, [1.0, 2.0])], "id long, vec array<double>"))
    with pytest.raises(ValueError):
        validate_vectors(spark.createDataFrame([(1, [float("nan")])], "id long, vec array<double>"))
    with pytest.raises(ValueError):
        cos_degrees(91)
    with pytest.raises(ValueError):
        I.build_index(vectors(spark, random_points(3, 2)), "unknown")


def test_save_and_load_keep_the_edges(spark, tmp_path):
    ix = I.build_index(vectors(spark, random_points(50, 3)), "nag", 2)
    I.save_index(ix, str(tmp_path / "ix"))
    back = I.load_index(spark, str(tmp_path / "ix"))
    assert sorted(I.index_edges(back).collect()) == sorted(I.index_edges(ix).collect())
    assert I.load_index(spark, str(tmp_path / "ix"), [0]).count() == 1


def test_vector_file_round_trip(spark, tmp_path):
    from anglegraph.sources.vectors import read_vecfile, write_vecfile

    x = random_points(20, 5).astype("f4")
    write_vecfile(str(tmp_path / "v.fvecs"), x)
    got = read_vecfile(spark, str(tmp_path / "v.fvecs")).orderBy("id").collect()
    assert np.array_equal(np.array([r["vec"] for r in got], "f4"), x)


def test_reverse_step_takes_a_far_free_edge_of_a_hub(spark):
    points = [(0, [0.0, 0.0]), *((i, [float(i), 0.0]) for i in range(1, 41)), (99, [-60.0, 0.0])]
    v = spark.createDataFrame(points, "id long, vec array<double>")
    edges = spark.createDataFrame([(i, 0, abs(x[0])) for i, x in points if i], "src long, dst long, dist double")
    got = N.reverse_refine(edges, v, 60.0, 2)
    assert [r["dst"] for r in got.where("src = 0").orderBy("rank").collect()] == [1, 99]


def test_sharded_search_is_set_against_one_graph(spark):
    r = np.random.default_rng(8)
    v = spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(r.random((300, 4)))], "id long, vec array<double>")
    rows = {(x["method"], x["layout"], x["probes"]) for x in X.w10_sharded(v, n_shards=3, k=5).collect()}
    assert rows == {*((m, *p) for m in ("nag", "nav_mrng", "ivf_pq") for p in (("one", 1), ("random", 3))), ("nag", "kmeans", 1)}


def test_exact_neighbours_of_many_equal_points(spark):
    from anglegraph.functions import graph_kernels as G
    from anglegraph.operators import neighbors as N

    d = spark.createDataFrame([(i, [1.0, 2.0]) for i in range(200, 0, -1)] + [(201, [1.0, 2.5])], "id long, vec array<double>").coalesce(1)
    q = spark.createDataFrame([(7, [1.0, 2.0])], "qid long, vec array<double>")
    assert [r["id"] for r in N.exact_knn(d, q, 3).orderBy("rank").collect()] == [1, 2, 3]
    assert [r["id"] for r in N.exact_knn(d, q, 3, exclude_self=True).orderBy("rank").collect()] == [1, 2, 3]
    x = np.ones((60, 3))
    assert G.exact_lists(x, 4)[10].tolist() == [0, 1, 2, 3] and G.exact_lists(x, 4)[1].tolist() == [0, 2, 3, 4]


def test_lune_rule_in_another_order():
    from anglegraph.functions import graph_kernels as G

    r = np.random.default_rng(4)
    x, visit = r.random((60, 2)), r.permutation(60)
    for p in range(60):
        kept = []
        d = ((x - x[p]) ** 2).sum(axis=1)
        for c in sorted(set(range(60)) - {p}, key=lambda i: visit[i]):
            if not any(d[k] < d[c] and ((x[k] - x[c]) ** 2).sum() < d[c] for k in kept):
                kept.append(c)
        assert G.greedy(x, p, np.array([i for i in range(60) if i != p]), None, visit=visit) == kept


@pytest.mark.parametrize("alpha", [60.0, 45.0, 30.0, 0.0, None])
def test_blocked_pruning_keeps_what_the_plain_rule_keeps(alpha):
    r = np.random.default_rng(6)
    cos = None if alpha is None else cos_degrees(alpha)
    for x in (r.standard_normal((90, 5)), r.integers(0, 6, (90, 2)).astype(float), np.vstack([r.random((40, 3))] * 2), np.ones((12, 2))):
        for visit in (None, r.permutation(len(x))):
            for p, kept, d2 in G.pruned_rows(x, np.arange(len(x)), cos, visit):
                every = np.delete(np.arange(len(x)), p)
                assert len(every) == len(kept) if alpha == 0 else G.greedy(x, p, every, cos, visit=visit) == kept.tolist()
                assert np.array_equal(d2, G.sq_to(x[p], x[kept]))


def test_exact_graph_is_built_by_many_tasks_and_shuffles_no_pairs(spark):
    x = random_points(150, 4)
    v = vectors(spark, x, np.arange(150) * 3 + 1).repartition(5)
    e = I.exact_graph(v, 60.0)
    assert e.rdd.getNumPartitions() > 1 and "Exchange" not in e._jdf.queryExecution().executedPlan().toString()
    got = {(r["src"], r["rank"]): r["dst"] for r in e.collect()}
    want = {(p * 3 + 1, i + 1): q * 3 + 1 for p in range(150) for i, q in enumerate(kept_of(x, p, 0.5))}
    assert got == want
    assert {(r["src"], r["dst"]) for r in I.index_edges(I.build_index(v, "exact_angle")).collect()} == {(s, d) for (s, _), d in want.items()}
    shards = {r["id"]: r["shard"] for r in I.shard_of(v, 3).collect()}
    several = I.index_edges(I.build_index(v, "mrng", 3)).collect()
    assert {shards[r["src"]] - shards[r["dst"]] for r in several} == {0} and {r["src"] for r in several} == set(shards)


def kept_of(x, p, cos, **more):
    return G.greedy(x, p, np.delete(np.arange(len(x)), p), cos, **more)


def test_violations_of_any_graph(spark):
    x = np.vstack([random_points(40, 3), random_points(5, 3)])
    x[40:] = x[:5]
    edges = [(p, q) for p in range(44) for q in (p + 1, (p * 7) % 45) if p != q]
    want = set()
    for p in range(45):
        out = [q for s, q in edges if s == p]
        want |= {(p, q) for q in range(45) if q != p and not any(((x[r] - x[q]) ** 2).sum() < ((x[p] - x[q]) ** 2).sum() for r in out)}
    got = N.monotonic_violations(spark.createDataFrame(edges, "src long, dst long"), vectors(spark, x))
    assert {tuple(r) for r in got.collect()} == want and len(want) > 45
    assert "CartesianProduct" not in (plan := got._jdf.queryExecution().toString()) and "BroadcastNestedLoopJoin" not in plan


def test_angle_of_a_degree_over_all_points(spark):
    from anglegraph.operators import relational as R

    v = vectors(spark, random_points(80, 6))
    every = v.selectExpr("id src").crossJoin(v.selectExpr("id cand")).where("src <> cand")
    got, want = I.exact_alpha_for_degree(v, 12), R.alpha_for_degree(every, v, 12)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
    assert got.rdd.getNumPartitions() > 1


def test_largest_products_and_ranges_by_blocks(spark):
    r = np.random.default_rng(2)
    x, q = r.integers(-3, 4, (300, 4)).astype(float), r.integers(-3, 4, (9, 4)).astype(float)
    v, asks = vectors(spark, x).repartition(3), X.queries_of(vectors(spark, q))
    want = [(i, k + 1, int(j), float(q[i] @ x[j])) for i in range(9) for k, j in enumerate(np.lexsort((np.arange(300), -(x @ q[i])))[:10])]
    got = N.exact_ip(v, asks, 10)
    assert sorted(map(tuple, got.collect())) == want
    near = N.range_search(v, asks, 3.0)  # many pairs stand at the radius itself
    dist = np.sqrt(((q[:, None] - x[None]) ** 2).sum(axis=2))
    assert sorted(map(tuple, near.collect())) == [(i, j, dist[i, j]) for i in range(9) for j in range(300) if dist[i, j] < 3.0]
    for plan in (got, near):
        text = plan._jdf.queryExecution().executedPlan().toString()
        assert "NestedLoop" not in text and "MapInArrow" in text and "Join" not in text


def test_grid_builds_its_indexes_at_once(spark, monkeypatch):
    import threading

    from anglegraph import workloads as X

    build, at_once = X.I.build_index, threading.Barrier(8)

    def meet(*args, **params):
        at_once.wait(timeout=20)
        return build(*args, **params)

    monkeypatch.setattr(X.I, "build_index", meet)
    v = spark.range(300).selectExpr("id", "array(sin(id), cos(3 * id), sin(7 * id)) as vec")
    assert X.w8_grid(v).count() == 16


def test_builds_at_once_pass_their_points_through_the_driver_one_by_one(spark, monkeypatch):
    import threading

    busy, threads, collect = threading.Lock(), set(), I.matrix_of

    def alone(*args):
        assert busy.acquire(blocking=False)
        threads.add(threading.current_thread())
        got = collect(*args)
        busy.release()
        return got

    monkeypatch.setattr(I, "matrix_of", alone)
    monkeypatch.setattr(I, "SPREAD_ROWS", 1)
    x = random_points(60, 4)
    v = vectors(spark, x[::-1], np.arange(60)[::-1] * 2).repartition(3)
    graphs = X._together(lambda m: sorted(map(tuple, I.index_edges(I.build_index(v, m)).select("src", "dst").collect())), ["mrng", "nag", "mrng", "nag"])
    assert len(threads) == 1 and graphs[:2] == graphs[2:]
    assert graphs[0] == sorted((p * 2, q * 2) for p in range(60) for q in kept_of(x, p, None))


@pytest.mark.parametrize("alpha", [30.0, 55.0, 60.0, 80.0])
def test_screened_pruning_keeps_what_the_plain_rule_keeps(alpha, monkeypatch):
    monkeypatch.setattr(G, "_others", lambda *_: pytest.fail("sums of differences of all points"))
    x = random_points(300, 20)
    for x in (x, np.round(x), np.vstack([x[:150] + 1000.0] * 2), x * 1e-9):
        for p, kept, d2 in G.pruned_rows(x, np.arange(0, 300, 30), cos_degrees(alpha)):
            assert kept.tolist() == kept_of(x, p, cos_degrees(alpha)) and (d2 == G.sq_to(x[p], x[kept])).all()


def test_rough_products_leave_lune_pruning_as_it_is(monkeypatch):
    r, kept_in = np.random.default_rng(3), G._pruned
    x = r.standard_normal((900, 20))
    met = []
    monkeypatch.setattr(G, "_others", lambda *_: pytest.fail("sums of differences of all points"))
    monkeypatch.setattr(G, "_pruned", lambda *a, **more: met.append(len(more["others"][0])) or kept_in(*a, **more))
    monkeypatch.setattr(G, "HEAD", 32)
    for x in (x, np.round(x), np.vstack([x[:150] + 1000.0] * 2), x * 1e-9):
        for visit in (None, r.permutation(len(x)), r.integers(0, 5, len(x))):
            for p, kept, d2 in G.pruned_rows(x, np.arange(0, len(x), 60), None, visit):
                assert kept.tolist() == kept_of(x, p, None, visit=visit) and (d2 == G.sq_to(x[p], x[kept])).all()
        if len(met) == 90:  # points without ties: most are never measured
            assert np.mean(met) < 200


@pytest.mark.parametrize("alpha", [None, 30.0, 60.0, 90.0])
def test_boxes_of_points_leave_pruning_as_it_is(alpha, monkeypatch):
    r, cos = np.random.default_rng(7), None if alpha is None else cos_degrees(alpha)
    wide, met, points = r.random((4000, 2)), [], G.Tiles.points
    monkeypatch.setattr(G, "_others", lambda *_: pytest.fail("sums of differences of all points"))
    monkeypatch.setattr(G.Tiles, "points", lambda self, tiles: met.append(len(tiles)) or points(self, tiles))
    at = np.arange(0, 4000, 200)
    got = [(p, kept.tolist()) for p, kept, _ in G.pruned_rows(wide, at, cos)]
    assert sum(met) < len(at) * len(G.Tiles(wide).low) / (8 if alpha is None else 1) and got[:3] == [(p, kept_of(wide, p, cos)) for p in at[:3].tolist()]
    for name, few in (("TILED_ROWS", 1), ("LEAF", 4), ("GROUP", 3)):
        monkeypatch.setattr(G, name, few)
    for x in (r.random((200, 2)), r.integers(0, 6, (150, 2)).astype(float), np.vstack([r.random((40, 3))] * 3), np.ones((20, 2)), r.random((90, 5)) * 1e-9, r.random((90, 2)) + 1e6):
        for p, kept, d2 in G.pruned_rows(x, np.arange(0, len(x), 5), cos):
            assert kept.tolist() == kept_of(x, p, cos) and np.array_equal(d2, G.sq_to(x[p], x[kept]))


def test_angle_of_a_degree_without_measuring_all_points(monkeypatch):
    r, grid = np.random.default_rng(8), [(cos_degrees(a), a) for a in (60.0, 50.0, 40.0, 30.0)]
    for x in (r.standard_normal((200, 20)), np.round(r.standard_normal((150, 20)) * 0.7), np.vstack([r.standard_normal((60, 20)) + 1000.0] * 2)):
        at = np.arange(0, len(x), 8)
        for target in (1, 12, 60, 119):
            want = [(p, G.degree_choice(x, p, target, grid)) for p in at.tolist()]
            assert list(G.degree_rows(x, at, target, grid)) == want
            for p, (alpha, n) in want[:4]:
                degrees = {a: len(kept_of(x, p, c)) for c, a in grid}
                assert min((abs(d - target), -a, d) for a, d in degrees.items()) == (abs(n - target), -alpha, n)
    monkeypatch.setattr(G, "_others", lambda *_: pytest.fail("sums of differences of all points"))
    assert len(list(G.degree_rows(x, at, 12, grid))) == len(at)


def test_points_without_a_closer_neighbour_by_rough_products(monkeypatch):
    r = np.random.default_rng(5)
    x, met = r.standard_normal((400, 20)), []
    for x in (x, np.round(x), np.vstack([x[:200] + 1000.0] * 2)):
        outs = [np.setdiff1d(r.permutation(len(x))[: p % 30], [p]) for p in range(len(x))]
        for p, q in G.unreached_rows(x, np.arange(len(x)), outs):
            assert q.tolist() == G.unreached(x, p, outs[p]).tolist()
    plain = G.unreached
    monkeypatch.setattr(G, "unreached", lambda x, p, out, q: met.append(len(q)) or plain(x, p, out, q))
    list(G.unreached_rows(r.standard_normal((400, 20)), np.arange(400), [np.delete(np.arange(400), p)[:60] for p in range(400)]))
    assert np.mean(met) < 50


def test_links_are_those_of_all_distances_without_taking_them_again(monkeypatch):
    def plain(x, graph, roots, cap):
        for root in roots:
            seen = G.reached(graph, root)
            while not seen.all():
                inside, outside = np.flatnonzero(seen), np.flatnonzero(~seen)
                spare = inside[[len(graph[p]) < cap for p in inside]]
                base = spare if len(spare) else inside
                near = [(float(d[j]), int(base[j]), int(b)) for b in outside[: G.WINDOW] for d in [sums(x[b], x[base])] for j in [int(d.argmin())]]
                graph[min(near)[1]].append(min(near)[2])
                seen = G.reached(graph, min(near)[2], seen)

    sums, monkeyed = G.sq_to, []
    monkeypatch.setattr(G, "WINDOW", 8)
    for x in (random_points(200, 5), np.round(random_points(200, 2)), np.repeat(random_points(50, 3), 4, axis=0)):
        for cap, near in ((1, 1), (2, 2), (3, 3), (4, 3)):
            want = [r.tolist() for r in G.exact_lists(x, near)]
            got = [list(r) for r in want]
            plain(x, want, [0, 60], cap)
            monkeypatch.setattr(G, "sq_to", lambda q, p: monkeyed.append(len(p)) or sums(q, p))
            links = G.strengthen(x, got, [0, 60], cap)
            monkeypatch.setattr(G, "sq_to", sums)
            assert got == want and links > 10
            assert cap == 1 or sum(monkeyed) < 60 * links
            monkeyed.clear()


@pytest.mark.parametrize("method", I.LISTED)
def test_graphs_of_many_tasks_are_those_of_one(spark, monkeypatch, method):
    v = vectors(spark, random_points(300, 6))
    for shards in (1, 3):
        one = I.build_index(v, method, shards)
        monkeypatch.setattr(I, "SPREAD_ROWS", 200)
        spread = []
        monkeypatch.setattr(I, "_spread", lambda *a, f=I._spread: spread.append(a[1]) or f(*a))
        many = I.build_index(v, method, shards)
        monkeypatch.undo()
        assert spread == [method]
        for columns in (["shard", "n", "n_edges", "max_degree", "links"],):
            assert sorted(one.select(columns).collect()) == sorted(many.select(columns).collect())
        assert sorted(I.index_edges(one).collect()) == sorted(I.index_edges(many).collect())
        assert all(r["t1"] > 0 and r["t2"] > 0 for r in many.select("t1", "t2").collect())


def test_queries_dealt_to_tasks_get_the_answers_of_one_task(spark, monkeypatch):
    from anglegraph import measures as M

    v = vectors(spark, random_points(200, 5))
    q = v.where("id % 2 = 0").selectExpr("id AS qid", "vec")
    for method, shards, more in (("nag", 1, {"exclude_self": True}), ("hnsw", 1, {}), ("scan", 3, {"n_probe": 1})):
        ix = I.build_index(v, method, shards)
        one = I.search_shards(ix, q, 5, 20, **more)
        monkeypatch.setattr(I, "SPLIT_QUERIES", 10)
        many = I.search_shards(ix, q, 5, 20, **more)
        assert one.rdd.getNumPartitions() <= 8 < many.rdd.getNumPartitions()
        assert sorted(one.collect()) == sorted(many.collect())
        assert [r["n_queries"] for r in M.search_seconds(ix, q, 5, 20).collect()] == [100] * shards
        monkeypatch.undo()


def test_methods_that_are_compared_are_built_at_once(spark, monkeypatch):
    import threading

    from anglegraph import measures as M

    v = vectors(spark, random_points(60, 3))
    build = X.I.build_index
    for work, methods, rows in ((X.w5_index_table, 5, 5), (M.build_memory, 4, 4), (X.w15_scan_share, 6, 6)):
        at_once = threading.Barrier(methods)

        def meet(*a, wait=at_once, **p):
            wait.wait(20)
            return build(*a, **p)

        monkeypatch.setattr(X.I, "build_index", meet)
        assert work(v).count() == rows
        monkeypatch.undo()
