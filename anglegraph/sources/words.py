"""Vectors of words: hashed counts of the words within two places, log-scaled, of length one."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

REACH = 2


def word_counts(df: DataFrame, text_col: str = "text", dim: int = 64) -> DataFrame:
    """(word, at, c): how often a neighbour of the word hashes to component `at`."""
    tokens = F.filter(F.split(F.lower(text_col), r"[^\p{L}]+"), lambda t: t != "")
    named = F.transform(tokens, lambda t: F.struct(t.alias("w"), (F.conv(F.substring(F.md5(t), 1, 4), 16, 10).cast("int") % dim).alias("h")))
    rows = df.select(named.alias("t")).where(F.size("t") > 1)
    n = F.size("t")
    pairs = F.flatten(F.array(*[F.zip_with(F.slice("t", 1, F.greatest(n - s, F.lit(0))), F.slice("t", s + 1, n), lambda a, b: F.struct(a["w"].alias("a"), a["h"].alias("ah"), b["w"].alias("b"), b["h"].alias("bh"))) for s in range(1, REACH + 1)]))
    p = rows.select(F.explode(pairs).alias("p")).where("p.a is not null and p.b is not null")
    both = p.select(F.explode(F.array(F.struct(F.col("p.a").alias("word"), F.col("p.bh").alias("at")), F.struct(F.col("p.b").alias("word"), F.col("p.ah").alias("at")))).alias("x"))
    return both.groupBy("x.word", "x.at").agg(F.count("*").alias("c"))


def word_vectors(df: DataFrame, text_col: str = "text", dim: int = 64, least: int = 5) -> DataFrame:
    """(id, word, uses, vec) of the words with `least` neighbours or more; id is 60 bits of the word's MD5."""
    c = word_counts(df, text_col, dim)
    x = F.log1p(F.col("c").cast("double"))
    sums = [F.sum(F.when(F.col("at") == i, x).otherwise(0.0)).alias(f"s{i}") for i in range(dim)]
    d = c.groupBy("word").agg(F.sum("c").alias("uses"), F.sqrt(F.sum(x * x)).alias("_n"), *sums).where(F.col("uses") >= least)
    wid = F.conv(F.substring(F.md5("word"), 1, 15), 16, 10).cast("long")
    return d.select(wid.alias("id"), "word", "uses", F.array(*[F.col(f"s{i}") / F.col("_n") for i in range(dim)]).alias("vec"))
