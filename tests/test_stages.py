import numpy as np
import pytest
from pyspark.sql import functions as F

from anglegraph import measures as M
from anglegraph import workloads as X
from anglegraph.functions import surface
from anglegraph.operators import index as I
from anglegraph.operators import neighbors as N
from anglegraph.operators import relational as R
from anglegraph.sources import words as W


def frame(spark, x):
    return spark.createDataFrame([(i, [float(c) for c in v]) for i, v in enumerate(x)], "id long, vec array<double>")


@pytest.fixture(scope="module")
def points():
    return np.random.default_rng(3).standard_normal((120, 5))


def test_frontier_search_answers_as_the_kernel(spark, points):
    v = frame(spark, points)
    base, q = X.base_and_queries(v)
    q = q.where("qid < 60")
    ix = I.build_index(base, "exact_angle", alpha=60.0)
    entry = N.pick_navigators(base, 1).select("node").first()["node"]
    entries = q.select("qid", F.lit(entry).alias("entry"))
    got = {(r["qid"], r["rank"]): r["id"] for r in R.frontier_search(I.index_edges(ix), base, q, entries, 5, 12).collect()}
    want = {(r["qid"], r["rank"]): r["id"] for r in I.search_index(ix, q, 5, 12).collect()}
    assert got == want and len(got) == 30


def test_frontier_search_reports_an_unfinished_search(spark, points):
    v = frame(spark, points[:20])
    e = I.index_edges(I.build_index(v, "exact_angle", alpha=60.0))
    q = X.queries_of(v.where("id = 7"))
    with pytest.raises(RuntimeError):
        R.frontier_search(e, v, q, q.select("qid", F.lit(0).cast("long").alias("entry")), 1, 20, max_rounds=1)


@pytest.mark.parametrize("radius", [0.5, 1.0])
def test_grid_join_finds_all_pairs(spark, points, radius):
    x = points[:, :2]
    d = ((x[:, None] - x[None]) ** 2).sum(axis=2)
    want = {(i, j) for i in range(len(x)) for j in range(len(x)) if d[i, j] <= radius**2}
    v = frame(spark, x)
    assert {(r["id"], r["other"]) for r in R.grid_range_join(v, v, radius, 2).collect()} == want


def test_alpha_for_degree_takes_the_closest(spark, points):
    v = frame(spark, points[:40])
    pairs = v.select(F.col("id").alias("src")).join(v.select(F.col("id").alias("cand")), F.col("src") != F.col("cand"))
    by = {a: {r["src"]: r["n"] for r in N.angle_prune(pairs, v, a).groupBy("src").agg(F.count("*").alias("n")).collect()} for a in (30.0, 60.0)}
    for r in R.alpha_for_degree(pairs, v, 9, (30.0, 60.0)).collect():
        assert abs(r["degree"] - 9) == min(abs(by[a][r["src"]] - 9) for a in by)


def test_ratio_at_a_precision(spark):
    c = spark.createDataFrame([("a", 1, 0.5, 100.0), ("a", 2, 1.0, 50.0), ("b", 1, 0.95, 10.0), ("c", 1, 0.1, 9.0)], "method string, size int, precision double, qps double")
    assert {r["method"]: r["qps"] for r in M.at_precision(c, 0.75).collect()} == {"a": 75.0, "b": 10.0}
    assert {r["method"]: r["ratio"] for r in M.speedup(c, "b", 0.75).collect()} == {"a": 7.5, "b": 1.0}


def test_build_reports_memory(spark, points):
    row = I.build_index(frame(spark, points), "nag").select("peak_mb").first()
    assert row["peak_mb"] > 0


@pytest.mark.parametrize("method", ["knn_graph_lsh", "pruned_knn"])
def test_seeded_and_pruned_graphs_find_neighbours(spark, points, method):
    base, q = X.base_and_queries(frame(spark, points))
    got = I.search_index(I.build_index(base, method), q, 5, 60)
    assert N.precision_at_k(got, N.exact_knn(base, q, 5), 5).agg(F.avg("precision")).first()[0] >= 0.85


def test_word_counts_by_hand(spark):
    d = spark.createDataFrame([("Ab cd, ab",), (None,), ("",), ("one",)], "text string")
    got = {r["word"]: r["n"] for r in W.word_counts(d).groupBy("word").agg(F.sum("c").alias("n")).collect()}
    assert got == {"ab": 4, "cd": 2}
    v = W.word_vectors(d, least=1).collect()
    assert all(abs(sum(x * x for x in r["vec"]) - 1) < 1e-9 for r in v)


def test_sql_surface(spark, points):
    surface.register(spark)
    assert spark.sql("SELECT vec_l2(array(0D, 3D), array(4D, 0D)) AS x").first()["x"] == 5.0
    base = frame(spark, points)
    I.build_index(base, "scan", 3).select("shard", "blob").createOrReplaceTempView("t_shards")
    given = ", ".join(f"{x!r}D" for x in points[4].tolist())
    rows = spark.sql(f"SELECT id FROM nearest_in_shards(TABLE(SELECT shard, blob FROM t_shards), array({given}), 4, 4) ORDER BY dist, id LIMIT 4").collect()
    assert [r["id"] for r in rows] == np.argsort(((points - points[4]) ** 2).sum(axis=1))[:4].tolist()


def test_range_join_of_copies_grows_with_copies_not_their_pairs(spark, tmp_path):
    from pyspark.sql import functions as F

    from anglegraph import stages

    some = [(1, 2, 905.0), (2, 3, 905.0), (3, 40, 905.0)]
    rows = [(k + 10 * i, size, price) for i in range(30) for k, size, price in some]
    spark.createDataFrame(rows, "p_partkey long, p_size int, p_retailprice double").write.parquet(str(tmp_path / "part.parquet"))
    got = stages.queries()["range_band_join"](spark, str(tmp_path))
    assert got.count() == 3 * 29 + 1  # every copy by one link, and the one pair of different vectors
    assert [tuple(r) for r in got.where("dist2 > 0").collect()] == [(1, 2, 400.0)]
    assert sorted(r["other"] for r in got.where(F.col("id") == 3).collect()) == [3 + 10 * i for i in range(1, 30)]


def test_recursive_count_goes_as_far_as_the_table(spark, tmp_path):
    from anglegraph import catalog

    spark.createDataFrame([(3.0,), (1.0,), (3.0,), (5.0,)], "l_quantity double").write.parquet(str(tmp_path / "lineitem.parquet"))
    got = catalog.queries()["op_recursive"](spark, str(tmp_path))
    assert sorted(tuple(r) for r in got.collect()) == [(1, 1), (2, None), (3, 2), (4, None), (5, 1)]
