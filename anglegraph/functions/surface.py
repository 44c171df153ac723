"""What SQL users call: distance functions, and a table function that searches the shards of an index."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

SUM = "aggregate(zip_with(a, b, (x, y) -> {term}), 0D, (s, x) -> s + x)"
FUNCTIONS = {
    "vec_l2": f"sqrt({SUM.format(term='(x - y) * (x - y)')})",
    "vec_l1": SUM.format(term="abs(x - y)"),
    "vec_dot": SUM.format(term="x * y"),
}


class NearestInShards:
    """Rows (shard, blob) of an index as a table argument; the answers of each shard for one vector."""

    def eval(self, row, vec, k, size):
        import numpy as np

        from anglegraph.operators.index import _load, search_shard

        s = _load(bytes(row["blob"]))
        pos, d, n, *_ = search_shard(s, np.array(vec, float), k, size)
        for p, v in zip(pos, d):
            yield row["shard"], int(s["ids"][p]), float(v) ** 0.5


def register(spark: SparkSession) -> None:
    """vec_l2, vec_l1, vec_dot (inlined by the optimizer) and nearest_in_shards in this session."""
    for name, body in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN {body}")
    spark.udtf.register("nearest_in_shards", udtf(NearestInShards, returnType="shard int, id long, dist double"))
