"""Quality rules, line first, in Spark expressions only.

Each line with a word is judged by three rules: punctuation (a short line must end a sentence),
navigation (menus and bars of links) and boilerplate (notices). Failing lines go; a document that
loses more than a stated share of its word characters with them is rejected, and so is one that
fails the base rules: too few words, or too many of its words in repeated three-word windows.

Defined results: null, empty or wordless text: 0 words, rejected by the base rules; repeated rows
give repeated results; null ids are kept; no rows: no rows. `clean_documents` keeps all columns.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

MIN_WORDS = 50
MAX_REPEAT = 50  # percent of words in repeated windows
MAX_LOSS = 50  # percent of word characters in failing lines
SHORT_LINE = 4  # words; a line of so many or fewer must end a sentence
MENU_WORDS = 12

# What ends a sentence, what menus and notices say.
SENTENCE_END = r"[.!?:;…\"'”’»)\]][\x20\x09-\x0D]*$"
MENU = r"(?i)^[\x20\x09-\x0D]*(home|menu|login|log in|sign in|sign up|next|previous|back to top|skip to content|share this|read more|site map|contact us|about us)\b"
NOTICE = r"(?i)(all rights reserved|privacy policy|terms of (use|service)|cookie (policy|settings)|uses cookies|enable javascript|subscribe to our newsletter|powered by|click here)"
SPACES = r"[\x20\x09-\x0D]+"
WORD = r"[^\x20\x09-\x0D]"


def _squeezed(text: Column) -> Column:
    """The words with one space between them."""
    return F.trim(F.regexp_replace(text, SPACES, " "))


def _count(squeezed: Column) -> Column:
    gaps = F.length(squeezed) - F.length(F.replace(squeezed, F.lit(" "), F.lit("")))
    return F.when(F.length(squeezed) > 0, gaps + 1).otherwise(0)


def line_fails(line: Column) -> Column:
    """Whether a line with a word breaks a rule."""
    n = _count(_squeezed(line))
    bar = F.length(F.regexp_replace(line, r"[^|»•]+", "")) * 3 >= n
    menu = (n <= MENU_WORDS) & line.rlike(MENU) & ~line.rlike(SENTENCE_END)
    bars = line.rlike(r"[|»•]") & bar & (n <= 3 * MENU_WORDS)
    bare = (n <= SHORT_LINE) & ~line.rlike(SENTENCE_END)
    notice = (n <= 2 * MENU_WORDS) & line.rlike(NOTICE)
    return bare | menu | bars | notice


def _repeat_words(d: DataFrame) -> DataFrame:
    """_n_repeat: words in three-word windows that the text has twice or more."""
    long_enough = F.col("_n") >= 3
    d = d.withColumn("_w", F.when(long_enough, F.split("_sq", " ")))
    window = lambda i: F.xxhash64(F.get("_w", i), F.get("_w", i + 1), F.get("_w", i + 2))
    d = d.withColumn("_h", F.when(long_enough, F.transform(F.sequence(F.lit(0), F.size("_w") - 3), window))).drop("_w")
    d = d.withColumn("_again", F.size(F.array_distinct("_h")) < F.size("_h"))
    pairs = F.sort_array(F.transform("_h", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
    d = d.withColumn("_s", F.when(F.col("_again"), pairs)).drop("_h")
    twice = F.filter("_s", lambda e, k: F.coalesce((k > 0) & (F.get("_s", F.greatest(k - 1, F.lit(0)))["h"] == e["h"]), F.lit(False)) | F.coalesce(F.get("_s", k + 1)["h"] == e["h"], F.lit(False)))
    d = d.withColumn("_p", F.sort_array(F.transform(twice, lambda e: e["i"]))).drop("_s")
    width = F.transform("_p", lambda p, k: F.least(F.lit(3), F.coalesce(F.get("_p", k + 1) - p, F.lit(3))))
    d = d.withColumn("_n_repeat", F.coalesce(F.aggregate(width, F.lit(0), lambda a, x: a + x), F.lit(0)))
    return d.drop("_p", "_again")


def _judged(docs: DataFrame) -> DataFrame:
    """The rows with the measures and the verdict in columns that begin with _."""
    text = F.coalesce(F.col("text"), F.lit(""))
    d = docs.withColumn("_sq", _squeezed(text))
    d = d.withColumn("_n", _count(F.col("_sq")))
    d = d.withColumn("_chars", F.when(F.col("_n") > 0, F.length("_sq") - F.col("_n") + 1).otherwise(0))
    d = d.withColumn("_symbols", F.length(F.regexp_replace(text, "[^#*$%&|<>]+", "")))
    d = d.withColumn("_lines", F.filter(F.split(text, "\n"), lambda x: x.rlike(WORD)))
    d = d.withColumn("_dup", F.size("_lines") - F.size(F.array_distinct("_lines")))
    d = d.withColumn("_bad", F.filter("_lines", line_fails))
    lost = F.aggregate(F.transform("_bad", lambda x: F.length(F.regexp_replace(x, SPACES, ""))), F.lit(0), lambda a, x: a + x)
    d = d.withColumn("_lost", lost).withColumn("_n_lines", F.size("_lines")).withColumn("_n_bad", F.size("_bad")).drop("_lines", "_bad")
    d = _repeat_words(d).drop("_sq")
    d = d.withColumn("_failed", (F.col("_n") < MIN_WORDS) | (100 * F.col("_n_repeat") > MAX_REPEAT * F.col("_n")))
    return d.withColumn("_kept", ~F.col("_failed") & (100 * F.col("_lost") <= MAX_LOSS * F.col("_chars")))


def judge_documents(docs: DataFrame) -> DataFrame:
    """The measures and verdict of each row of (doc_id, text)."""
    d = _judged(docs.select("doc_id", "text"))
    names = {"_n": "n_words", "_chars": "word_chars", "_symbols": "n_symbols", "_dup": "n_dup_lines", "_n_repeat": "n_repeat_words"}
    more = {"_n_lines": "n_lines", "_n_bad": "n_bad_lines", "_lost": "lost_chars"}
    numbers = lambda m: [F.col(a).cast("long").alias(b) for a, b in m.items()]
    return d.select("doc_id", *numbers(names), F.col("_failed").alias("base_failed"), F.col("_kept").alias("kept"), *numbers(more))


def clean_documents(docs: DataFrame) -> DataFrame:
    """The kept rows, all columns, without the failing lines of their texts."""
    lines = F.filter(F.split("text", "\n"), lambda x: ~(x.rlike(WORD) & line_fails(x)))
    kept = _judged(docs).where("_kept").withColumn("text", F.array_join(lines, "\n"))
    return kept.select(*docs.columns)
