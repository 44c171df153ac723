"""Timed measures: queries per second of one thread, peak memory, and ratios at a given precision."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .operators import index as I
from .plans.lineage import cut
from .workloads import SWEEP, _labelled, _together, _union, base_and_queries, measured


def search_seconds(index: DataFrame, queries: DataFrame, k: int, size: int) -> DataFrame:
    """(shard, n_queries, seconds, peak_mb): time in the search kernel of one thread, without Spark's own.

    peak_mb is the most memory that the worker's process ever held. The queries are a bounded set.
    """
    def timed(shard, s, block):
        import resource
        import time

        began = time.perf_counter()
        for q in block[1]:
            I.search_shard(s, q, k, size)
        took = time.perf_counter() - began
        peak = resource.getrusage(resource.RUSAGE_SELF).ru_maxrss / 1024
        return pd.DataFrame({"shard": [shard], "n_queries": [len(block[1])], "seconds": [took], "peak_mb": [peak]})

    parts = [I.each_shard(index, block, timed, "shard int, n_queries long, seconds double, peak_mb double") for block in I._query_blocks(queries.select("qid", "vec"))]
    return _union(parts).groupBy("shard").agg(F.sum("n_queries").alias("n_queries"), F.sum("seconds").alias("seconds"), F.max("peak_mb").alias("peak_mb"))


def rate_curve(vectors: DataFrame, method: str, k: int = 10, **params) -> DataFrame:
    """(method, size, precision, n_dist, qps): the curve of a method; qps of one thread over all shards."""
    from .operators.neighbors import exact_knn

    base, q = base_and_queries(vectors)
    truth = cut(exact_knn(base, q, k))
    ix = I.build_index(base, method, **params)
    out = []
    for size in SWEEP[method]:
        rate = search_seconds(ix, q, k, size).agg((F.max("n_queries") / F.sum("seconds")).alias("qps"))
        row = measured(ix, q, truth, k, size).crossJoin(rate)  # one row each
        out.append(_labelled(row.select("precision", "n_dist", "qps"), method=method, size=size))
    return _union(out)


def at_precision(curves: DataFrame, precision: float, value: str = "qps") -> DataFrame:
    """(method, value): interpolated where a curve first crosses the precision; methods that never do have no row."""
    w = Window.partitionBy("method").orderBy("size")
    d = curves.withColumn("p0", F.lag("precision").over(w)).withColumn("v0", F.lag(value).over(w))
    cross = d.where((F.col("precision") >= precision) & (F.col("p0").isNull() | (F.col("p0") < precision)))
    share = (precision - F.col("p0")) / (F.col("precision") - F.col("p0"))
    got = F.when(F.col("p0").isNull(), F.col(value)).otherwise(F.col("v0") + share * (F.col(value) - F.col("v0")))
    return cross.groupBy("method").agg(F.min_by(got, "size").alias(value))


def speedup(curves: DataFrame, rival: str, precision: float, value: str = "qps") -> DataFrame:
    """(method, ratio): a method's value over the rival's at one precision."""
    at = at_precision(curves, precision, value)
    base = at.where(F.col("method") == rival).select(F.col(value).alias("base"))
    return at.crossJoin(base).select("method", (F.col(value) / F.col("base")).alias("ratio"))  # one rival row


def build_memory(vectors: DataFrame, methods=("nag", "nag_on_the_fly", "nav_mrng", "hnsw")) -> DataFrame:
    """(method, t1, t2, blob_bytes, peak_mb) of a build; the peak is that of the worker's process so far."""
    return _union(_together(lambda m: I.build_index(vectors, m).select("method", "t1", "t2", F.octet_length("blob").alias("blob_bytes"), "peak_mb"), list(methods)))
