"""Vector tables: loading, validation, and the views of the given tables as (id, vec, ...)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.geometry import norm, portable_hash


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def load_vectors(spark, path: str, id_col: str = "id", vec_col: str = "vec") -> DataFrame:
    """Only the two columns are read."""
    return spark.read.parquet(path).select(F.col(id_col).cast("long").alias("id"), F.col(vec_col).alias("vec"))


def validate_vectors(df: DataFrame, dim: int | None = None) -> int:
    """The common dimension; raises on null, mixed dimension, NaN or infinity."""
    bad = F.exists("vec", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    row = df.agg(F.min(F.size("vec")).alias("low"), F.max(F.size("vec")).alias("high"), F.sum((F.col("vec").isNull() | F.coalesce(bad, F.lit(True))).cast("int")).alias("bad")).first()
    if row["bad"] or row["low"] != row["high"] or (dim is not None and row["low"] not in (None, dim)):
        raise ValueError(f"vectors need one dimension{f' of {dim}' if dim else ''} and finite values: {row.asDict()}")
    return row["low"] or 0


def dedupe_vectors(df: DataFrame) -> tuple[DataFrame, DataFrame]:
    """One row for each distinct vector (the smallest id), and the map (id, rep) of all ids."""
    reps = df.groupBy("vec").agg(F.min("id").alias("id"))
    return reps.select("id", "vec"), df.select("id", "vec").join(reps.withColumnRenamed("id", "rep"), "vec").select("id", "rep")


def expand_duplicates(answers: DataFrame, copies: DataFrame) -> DataFrame:
    """Answers over representatives, with every copy at the same distance."""
    return answers.withColumnRenamed("id", "rep").join(copies, "rep").drop("rep")


def normalize_l2(df: DataFrame) -> DataFrame:
    n = norm("vec")
    return df.withColumn("vec", F.transform("vec", lambda x: x.cast("double") / n))


def emb(spark, sf_dir) -> DataFrame:
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"), "label")


def line4(spark, sf_dir) -> DataFrame:
    d = table(spark, sf_dir, "lineitem")
    whole = lambda c, a, b: F.round(F.col(c) * a) * b
    key = ((F.col("l_orderkey") * 8 + F.col("l_linenumber")) * 20000 + F.col("l_partkey")) * 1000 + F.col("l_suppkey")
    vec = F.array(whole("l_quantity", 1, 200000.0), whole("l_extendedprice", 100, 1.0), whole("l_discount", 100, 1000000.0), whole("l_tax", 100, 1200000.0))
    return d.select(key.alias("id"), vec.alias("vec")).groupBy("id").agg(F.min("vec").alias("vec"))


def part2(spark, sf_dir) -> DataFrame:
    d = table(spark, sf_dir, "part")
    return d.select(F.col("p_partkey").alias("id"), F.array((F.col("p_size") * 20).cast("double"), F.round((F.col("p_retailprice") - 900) * 10)).alias("vec"))


def text_vectors(df: DataFrame, id_col: str, text_col: str, dim: int = 64) -> DataFrame:
    """Mean of fixed signs of each token: word order and case do not count. Texts without tokens have no row."""
    token = F.explode(F.filter(F.split(F.lower(text_col), r"[^\p{L}]+"), lambda t: t != ""))
    words = df.select(F.col(id_col).alias("id"), token.alias("t")).groupBy("id", "t").agg(F.count("*").alias("c"))
    h = words.withColumn("h", F.conv(F.substring(F.md5("t"), 1, 8), 16, 10).cast("long")).withColumn("g", F.conv(F.substring(F.md5("t"), 9, 8), 16, 10).cast("long"))
    bit = lambda i: F.shiftright("h" if i < 32 else "g", i % 32).bitwiseAND(F.lit(1)) * 2 - 1
    sums = h.groupBy("id").agg(F.sum("c").alias("n"), *[F.sum(F.col("c") * bit(i)).alias(f"s{i}") for i in range(dim)])
    vec = F.array(*[F.col(f"s{i}") / F.col("n") / (dim**0.5) for i in range(dim)])
    return sums.select("id", vec.alias("vec"))


def page_text(spark, sf_dir) -> DataFrame:
    d = table(spark, sf_dir, "pages")
    return d.select(F.col("page_id").alias("id"), F.regexp_replace("html", "<[^>]*>", " ").alias("text"))


def cust_vectors(spark, sf_dir) -> DataFrame:
    """Customers with orders: orders, mean price and discount, share returned, balance, on fixed scales."""
    o, li = table(spark, sf_dir, "orders"), table(spark, sf_dir, "lineitem")
    lines = li.groupBy("l_orderkey").agg(F.sum("l_extendedprice").alias("price"), F.sum("l_discount").alias("disc"), F.sum((F.col("l_returnflag") == "R").cast("int")).alias("back"), F.count("*").alias("n"))
    per = o.join(lines, o["o_orderkey"] == lines["l_orderkey"]).groupBy("o_custkey").agg(F.count("*").alias("orders"), F.sum("price").alias("price"), F.sum("disc").alias("disc"), F.sum("back").alias("back"), F.sum("n").alias("n"))
    c = table(spark, sf_dir, "customer").select("c_custkey", "c_acctbal")
    d = per.join(c, per["o_custkey"] == c["c_custkey"])
    return d.select(F.col("c_custkey").alias("id"), F.array(F.col("orders") / 40.0, F.col("price") / F.col("n") / 100000.0, F.col("disc") / F.col("n") * 10.0, F.col("back") / F.col("n"), F.col("c_acctbal") / 10000.0).alias("vec"))


def event_vectors(df: DataFrame) -> DataFrame:
    kinds = ["click", "error", "purchase", "signup", "view"]
    turn = F.hour("ts") * (2 * 3.141592653589793 / 24)
    vec = F.array(F.col("value") / 500, F.sin(turn), F.cos(turn), *[(F.col("event_type") == k).cast("double") for k in kinds])
    return df.select("event_id", "ts", "user_id", vec.alias("vec"))


def split(df: DataFrame, mod: int = 100, pick: int = 37) -> tuple[DataFrame, DataFrame]:
    """The training and validation parts of a fixed 99:1 split."""
    return df.where(F.col("id") % mod != pick), df.where(F.col("id") % mod == pick)


def sample_hash(df: DataFrame, fraction: float, seed: int = 0) -> DataFrame:
    """Nested subsets: a larger fraction holds every smaller one."""
    return df.where(portable_hash("id", seed) < F.lit(int(fraction * 2147483648)))


def write_vecfile(path: str, rows) -> None:
    """Vectors as int32 dimension and float32 payload, one after the other."""
    import numpy as np

    with open(path, "wb") as f:
        for r in rows:
            f.write(np.int32(len(r)).tobytes() + np.asarray(r, "<f4").tobytes())


def read_vecfile(spark: SparkSession, path: str) -> DataFrame:
    """(id, vec) of such a file; Spark splits it by records of fixed length, ids count from 0."""
    import numpy as np
    import pyarrow as pa

    head = spark.read.format("binaryFile").load(path).select(F.substring("content", 1, 4).alias("h"), "length").first()
    dim = int(np.frombuffer(bytes(head["h"]), "<i4")[0])
    files = spark.read.format("binaryFile").load(path).select("content")

    def run(batches):
        for b in batches:
            for c in b.column("content"):
                raw = np.frombuffer(c.as_py(), "<f4").reshape(-1, dim + 1)[:, 1:]
                for a in range(0, len(raw), 10000):
                    part = raw[a : a + 10000]
                    yield pa.RecordBatch.from_pydict({"id": pa.array(range(a, a + len(part)), pa.int64()), "vec": pa.array(part.tolist(), pa.list_(pa.float32()))})

    return files.mapInArrow(run, "id long, vec array<float>")
