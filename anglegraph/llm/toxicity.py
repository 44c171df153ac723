"""Toxicity from class-conditional Kneser-Ney models.

Two pairs of models, of toxic and of ordinary texts, each give a document a length-normalised log
likelihood ratio; a logistic curve of the two, fitted on texts that the models have not seen, gives the score.

* Words and pairs of words: a pair backs off to the class's continuation counts of its second word, and
  these to the counts of all words of all documents, which both classes share. That table is gathered
  from every document and grows with the corpus; it stays distributed. Where a word is in no labelled
  text, its shared probability is in both likelihoods and cancels, so only the rows of words that the
  labelled sample holds are joined out of it and sent along.
* Bytes of words: a byte is predicted from the five before it in its word, so stems and endings count,
  not only whole words. Six bytes back off to the class's continuation counts of five and of four, and
  these to three-byte counts that both classes share, taken over all documents.

The models are fitted on at most FIT_ROWS labelled rows of a class (the first by a hash of the id),
the curve on at most CURVE_ROWS of another fold, where each row weighs as many labelled rows of its
class as it stands for, so that a score does not depend on which class the bound cuts; these bounds
are parameters. So the expressions of
the models are bounded by that sample, and so is their broadcast. Six-byte expressions and pairs of
words seen once are left to the backoff.

Only labels train: rows whose crc32(id) mod 5 is 0 are held out, fold 1 fits the curve, the others
the models. Source, language and ids are no inputs of a score. A document with several labels is
toxic if one says so; null labels say nothing.

Defined results: null or empty text: the score of a ratio of 0; repeated rows score alike; null ids
are held out of training; no rows: no rows; without labels of both classes every score is below 0.5
and nothing is rejected, and so where the curve's texts, being few, would make the score fall as the
ratio rises: all scores are then the base rate, below 0.5.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kernels as K
from .common import n_blocks, row_ranges, written

FIT_ROWS = 10_000
CURVE_ROWS = 4_000
CHUNK = 2 << 20  # bytes of text whose words are scored together
WORDS_HELD = 2 << 20  # prints of words that a task holds before it sends them
ORDER = 6  # bytes of the longest expression, the predicted one included
SHARED = 3  # bytes of the shared counts


def fold(column) -> F.Column:
    return F.crc32(F.col(column).cast("string").cast("binary")) % 5


def _words(texts, pw: K.Powers):
    """Distinct words as one padded buffer, the place of each text word among them, its row, and the prints of the words."""
    buf, offsets = K.text_buffer(texts)
    low = K.LOWER[buf]
    starts, ends, rows = K.word_spans(low, offsets, K.ALNUM_WORD)
    prints = K.word_prints(low, starts, ends, pw)
    known, first, place = np.unique(prints, return_index=True, return_inverse=True)
    a, n = starts[first], (ends - starts)[first]
    # five bytes before each word (four zeros and a space), one space after it
    begin = np.concatenate([[0], np.cumsum(n + ORDER)])
    out = np.zeros(int(begin[-1]) + 2, np.uint8)
    out[begin[:-1] + ORDER - 2] = 0x20
    inner = np.repeat(begin[:-1] + ORDER - 1 - (np.cumsum(n) - n), n) + np.arange(n.sum())
    source = np.repeat(a - (np.cumsum(n) - n), n) + np.arange(n.sum())
    out[inner] = low[source]
    out[begin[1:] - 1] = 0x20
    return out, begin, n + 1, place, rows, len(offsets) - 1, known


def _grams(out: np.ndarray, begin: np.ndarray, n: np.ndarray):
    """The six bytes that end at each predicted byte (first byte lowest), and the word of each."""
    m = int(begin[-1])
    if not m:
        return np.zeros(0, K.U), np.zeros(0, np.int64)
    view = np.ndarray((m - ORDER + 1,), "<u8", buffer=np.ascontiguousarray(out).data, strides=(1,))
    word = np.repeat(np.arange(len(n)), n)
    at = np.repeat(begin[:-1] - (np.cumsum(n) - n), n) + np.arange(n.sum())
    return view[at] & K.U((1 << 8 * ORDER) - 1), word


def _sample(docs: DataFrame, labels: DataFrame, fit_rows: int, curve_rows: int) -> DataFrame:
    """(toxic, curve, text, weight) of a bounded sample of labelled rows outside the held-out fold; a weight is a class's rows over those taken."""
    labs = labels.where(F.col("doc_id").isNotNull() & F.col("toxic").isNotNull() & (fold("doc_id") != 0))
    labs = labs.groupBy("doc_id").agg(F.max(F.col("toxic").cast("int")).alias("toxic"))
    sizes = {tuple(r)[:2]: r["count"] for r in labs.groupBy("toxic", (fold("doc_id") == 1).alias("curve")).count().collect()}
    pick = None
    for toxic in (0, 1):
        for curve, n in ((True, curve_rows), (False, fit_rows)):
            some = labs.where((F.col("toxic") == toxic) & ((fold("doc_id") == 1) == curve))
            some = some.orderBy(F.xxhash64("doc_id"), "doc_id").limit(n).select("doc_id", "toxic", F.lit(curve).alias("curve"), F.lit(max(1.0, sizes.get((toxic, curve), 0) / max(1, n))).alias("weight"))
            pick = some if pick is None else pick.unionAll(some)
    return docs.select("doc_id", "text").join(F.broadcast(pick), "doc_id").select("toxic", "curve", "text", "weight")


def _expressions(sample: DataFrame) -> DataFrame:
    """(g, c0, c1): counts of each six-byte expression by class."""

    def count(batches):
        pw = K.Powers()
        for batch in batches:
            toxic = batch.column(0).to_numpy(zero_copy_only=False)
            _, offsets = K.text_buffer(batch.column(2))
            for a, b in row_ranges(offsets, CHUNK):
                out, begin, n, place, rows, *_ = _words(batch.column(2).slice(a, b - a), pw)
                grams, word = _grams(out, begin, n)
                keys, at = np.unique(grams, return_inverse=True)
                cols = []
                for c in (0, 1):
                    times = np.bincount(place[toxic[a:b][rows] == c], minlength=len(n))
                    cols.append(pa.array(np.bincount(at, times[word], len(keys)).astype(np.int64)))
                yield pa.RecordBatch.from_arrays([pa.array(keys.view(np.int64)), *cols], names=["g", "c0", "c1"])

    found = sample.where(~F.col("curve")).mapInArrow(count, "g long, c0 long, c1 long")
    return found.groupBy("g").agg(F.sum("c0").alias("c0"), F.sum("c1").alias("c1"))


def _shared_counts(docs: DataFrame) -> DataFrame:
    """(g, n): how often each three-byte expression occurs in all documents; at most 256^3 rows."""

    def count(batches):
        pw = K.Powers()
        for batch in batches:
            _, offsets = K.text_buffer(batch.column(0))
            for a, b in row_ranges(offsets, CHUNK):
                out, begin, n, place, *_ = _words(batch.column(0).slice(a, b - a), pw)
                grams, word = _grams(out, begin, n)
                keys, at = np.unique(grams >> K.U(8 * (ORDER - SHARED)), return_inverse=True)
                total = np.bincount(at, np.bincount(place, minlength=len(n))[word], len(keys)).astype(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(keys.view(np.int64)), pa.array(total)], names=["g", "n"])

    return docs.select("text").mapInArrow(count, "g long, n long").groupBy("g").agg(F.sum("n").alias("n"))


def _pairs(place: np.ndarray, rows: np.ndarray, known: np.ndarray):
    """The prints of each word and of the word before it in its text (0 for the first, which has no context), and of the pair."""
    word = known[place]
    before = np.zeros(len(word), K.U)
    before[1:] = np.where(rows[1:] == rows[:-1], word[:-1], K.U(0))
    return before, word, K.mix(before * K.U(K.BASES[0]) + K.mix(word))


def _word_pairs(sample: DataFrame) -> DataFrame:
    """(pair, before, word, c0, c1): counts of each pair of words by class."""

    def count(batches):
        pw = K.Powers()
        for batch in batches:
            toxic = batch.column(0).to_numpy(zero_copy_only=False)
            _, offsets = K.text_buffer(batch.column(2))
            for a, b in row_ranges(offsets, CHUNK):
                *_, place, rows, _, known = _words(batch.column(2).slice(a, b - a), pw)
                before, word, pair = _pairs(place, rows, known)
                keys, first, at = np.unique(pair, return_index=True, return_inverse=True)
                counts = [np.bincount(at[toxic[a:b][rows] == c], minlength=len(keys)).astype(np.int64) for c in (0, 1)]
                cols = [keys.view(np.int64), before[first].view(np.int64), word[first].view(np.int64), *counts]
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in cols], names=["pair", "before", "word", "c0", "c1"])

    found = sample.where(~F.col("curve")).mapInArrow(count, "pair long, before long, word long, c0 long, c1 long")
    return found.groupBy("pair").agg(F.min("before").alias("before"), F.min("word").alias("word"), F.sum("c0").alias("c0"), F.sum("c1").alias("c1"))


def corpus_words(docs: DataFrame) -> DataFrame:
    """(word, n): how often each word, by its print, occurs in all documents; as many rows as the corpus has words.

    Tasks merge the words of their batches and send them packed, by key range, with their counts.
    """
    buckets = n_blocks(docs.select("text"))

    def merged(parts):
        keys, at = np.unique(np.concatenate([k for k, _ in parts]), return_inverse=True)
        return keys, np.bincount(at, np.concatenate([n for _, n in parts]), len(keys)).astype(np.int64)

    def count(batches):
        pw, held = K.Powers(), []

        def flush():
            import zstandard

            keys, n = merged(held)
            cuts = K.bucket_cuts(keys, buckets)
            full = np.flatnonzero(cuts[1:] > cuts[:-1])
            cols = [pa.array(full, pa.int32()), pa.array([K.pack_sorted(keys[cuts[b] : cuts[b + 1]]) for b in full], pa.binary()), pa.array([zstandard.compress(n[cuts[b] : cuts[b + 1]].tobytes(), 3) for b in full], pa.binary())]
            return pa.RecordBatch.from_arrays(cols, names=["bucket", "keys", "n"])

        for batch in batches:
            _, offsets = K.text_buffer(batch.column(0))
            for a, b in row_ranges(offsets, CHUNK):
                *_, place, _, _, known = _words(batch.column(0).slice(a, b - a), pw)
                held.append((known, np.bincount(place, minlength=len(known))))
            if sum(len(k) for k, _ in held) > WORDS_HELD:
                yield flush()
                held.clear()
        if held:
            yield flush()

    def meet(rows: pa.Table) -> pa.Table:
        import zstandard

        keys, n = merged([(K.unpack_sorted(k.as_py()), np.frombuffer(zstandard.decompress(c.as_py()), np.int64)) for k, c in zip(rows.column("keys"), rows.column("n"))])
        return pa.table({"word": keys.view(np.int64), "n": n})

    sent = docs.select("text").mapInArrow(count, "bucket int, keys binary, n binary")
    return sent.groupBy("bucket").applyInArrow(meet, "word long, n long")


def _sorted_columns(df: DataFrame, key: str) -> dict:
    """The columns of a bounded table as arrays, by ascending key."""
    table = df.toArrow()
    cols = {c: table.column(c).to_numpy() for c in table.column_names}
    cols[key] = cols[key].astype(np.int64).view(K.U)
    order = np.argsort(cols[key])
    return {c: v[order] for c, v in cols.items()}


class WordModel:
    """Pairs of words over words over the shared counts, for both classes."""

    def __init__(self, pairs: dict, words: dict, sums: dict):
        """pairs: pair, before, c0, c1; words: word, continuations k, contexts b, shared n; sums: over what the sample and the corpus hold."""
        self.words, self.pairs = words["word"], pairs["pair"]
        shared = (words["n"].astype(float) + 0.5) / (sums["total"] + 0.5 * sums["kinds"])
        self.first = np.zeros((len(self.words) + 1, 2))  # the last row: a word left to the backoff, whose shared part cancels
        self.parts = np.zeros((len(self.pairs) + 1, 2))
        self.backoff = np.ones((len(self.words) + 1, 2))
        at = _find(self.words, pairs["before"].astype(np.int64).view(K.U))
        for c in (0, 1):
            d = _discount(sums[f"k1_{c}"], sums[f"k2_{c}"])
            whole = max(1.0, sums[f"k_{c}"])
            backoff = max(1e-9, d * sums[f"kinds_{c}"] / whole)
            self.first[:-1, c] = np.maximum(words[f"k{c}"].astype(float) - d, 0) / whole + backoff * shared
            self.first[-1, c] = backoff / (sums["total"] + 1)
            seen = np.append(words[f"b{c}"].astype(float), np.inf)
            self.parts[:-1, c] = np.maximum(pairs[f"c{c}"] - _discount(sums[f"n1_{c}"], sums[f"n2_{c}"]), 0) / np.maximum(1.0, seen[at])
            self.backoff[:, c] = np.maximum(1e-9, 1 - np.bincount(at, self.parts[:-1, c], len(self.words) + 1))

    def ratios(self, place, rows, known, n_rows: int) -> np.ndarray:
        """Log ratio of toxic to ordinary likelihood by text."""
        mine = _find(self.words, known)
        _, _, pair = _pairs(place, rows, known)
        before = np.full(len(place), len(self.words))
        before[1:] = np.where(rows[1:] == rows[:-1], mine[place[:-1]], len(self.words))
        p = self.parts[_find(self.pairs, pair)] + self.backoff[before] * self.first[mine[place]]
        return np.bincount(rows, np.log(p[:, 1]) - np.log(p[:, 0]), n_rows)


def _fit_words(docs: DataFrame, sample: DataFrame) -> WordModel:
    """The counts of pairs and words of the sample, and of its words those of all documents."""
    pairs = written(_word_pairs(sample), "toxic-pairs")
    shared = written(corpus_words(docs), "toxic-words")
    count = lambda c, n, name: F.sum((F.col(c) == n).cast("long")).alias(name)
    sums = shared.agg(F.sum("n").alias("total"), F.count("*").alias("kinds")).first().asDict()
    after = pairs.groupBy("word").agg(*[F.sum((F.col(f"c{c}") > 0).cast("long")).alias(f"k{c}") for c in (0, 1)])
    after = written(after, "toxic-after")
    for c in (0, 1):
        sums |= pairs.agg(count(f"c{c}", 1, f"n1_{c}"), count(f"c{c}", 2, f"n2_{c}")).first().asDict()
        sums |= after.agg(count(f"k{c}", 1, f"k1_{c}"), count(f"k{c}", 2, f"k2_{c}"), F.sum(f"k{c}").alias(f"k_{c}"), F.sum((F.col(f"k{c}") > 0).cast("long")).alias(f"kinds_{c}")).first().asDict()
    # expressions seen once are left to the backoff
    before = pairs.groupBy(F.col("before").alias("word")).agg(*[F.sum(f"c{c}").alias(f"b{c}") for c in (0, 1)])
    words = after.where("k0 + k1 > 1").join(before, "word", "left").join(shared, "word", "left").fillna(0)
    known = words.select(F.col("word").alias("before"))
    kept = pairs.where("c0 + c1 > 1 and before <> 0").select("pair", "before", "c0", "c1").join(known, "before", "left_semi")
    return WordModel(_sorted_columns(kept, "pair"), _sorted_columns(words, "word"), {k: v or 0 for k, v in sums.items()})


def _find(table: np.ndarray, keys: np.ndarray) -> np.ndarray:
    """The place of each key in a sorted table, or its length."""
    if not len(table):
        return np.zeros(len(keys), np.int64)
    at = np.searchsorted(table, keys)
    at[at == len(table)] = 0
    return np.where(table[at] == keys, at, len(table))


class Level:
    """One order of both models: discounted parts by expression, backoff weights by context."""

    def __init__(self, order: int, grams: np.ndarray, counts: np.ndarray, least: int = 0):
        self.order = order
        context = grams & K.U((1 << 8 * (order - 1)) - 1)
        self.contexts, at = np.unique(context, return_inverse=True)
        self.backoff = np.ones((len(self.contexts) + 1, 2), np.float32)
        keep = counts.sum(axis=1) > least
        self.grams = grams[keep]
        self.parts = np.zeros((len(self.grams) + 1, 2), np.float32)
        for c in (0, 1):
            n = counts[:, c].astype(float)
            total = np.maximum(1.0, np.bincount(at, n, len(self.contexts)))
            part = np.where(keep, np.maximum(n - _discount((n == 1).sum(), (n == 2).sum()), 0), 0) / total[at]
            self.parts[:-1, c] = part[keep]
            self.backoff[:-1, c] = np.maximum(1e-9, 1 - np.bincount(at, part, len(self.contexts)))

    def over(self, grams: np.ndarray, lower: np.ndarray) -> np.ndarray:
        """Probabilities of both classes from those of the order below."""
        keys = grams >> K.U(8 * (ORDER - self.order))
        contexts = keys & K.U((1 << 8 * (self.order - 1)) - 1)
        return self.parts[_find(self.grams, keys)] + self.backoff[_find(self.contexts, contexts)] * lower


class Model:
    """The levels from the shared counts up, and the curve."""

    def __init__(self, shared: tuple, levels: list, words: WordModel | None = None, curve=(-1e-9, 0.0, 0.0)):
        self.shared, self.levels, self.words, self.curve = shared, levels, words, curve

    def ratios(self, texts, pw: K.Powers) -> np.ndarray:
        """Log ratios of toxic to ordinary likelihood by text, of its bytes and of its words, over the number of bytes predicted."""
        out, begin, n, place, rows, n_rows, known = _words(texts, pw)
        if not len(n) or not self.levels:
            return np.zeros((n_rows, 2))
        grams, word = _grams(out, begin, n)
        keys, p = self.shared
        p = p[_find(keys, grams >> K.U(8 * (ORDER - SHARED)))][:, None]
        for level in self.levels:
            p = level.over(grams, p)
        ratio = np.bincount(word, np.log(p[:, 1]) - np.log(p[:, 0]), len(n))
        both = np.stack([np.bincount(rows, ratio[place], n_rows), self.words.ratios(place, rows, known, n_rows)], axis=1)
        return both / np.maximum(1, np.bincount(rows, n[place], n_rows))[:, None]

    def scores(self, texts, pw: K.Powers) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.curve[0] + self.ratios(texts, pw) @ np.array(self.curve[1:]), -60, 60)))


def _discount(n1: float, n2: float) -> float:
    return n1 / (n1 + 2 * n2) if n1 else 0.5


def _fit_curve(x: np.ndarray, y: np.ndarray, weight: np.ndarray | None = None) -> tuple:
    """Logistic regression on one or more inputs by Newton steps, of rows with weights: the base and a slope for each input."""
    x = x[:, None] if x.ndim == 1 else x
    w = np.ones(len(x)) if weight is None else weight
    if not 0 < y.sum() < len(y):
        return -1e-9, *[0.0] * x.shape[1]
    spread = np.sqrt(np.average((x - np.average(x, axis=0, weights=w)) ** 2, axis=0, weights=w))
    scale, used = np.maximum(1e-9, spread), list(range(x.shape[1]))
    while used:
        z = np.concatenate([np.ones((len(x), 1)), (x / scale)[:, used]], axis=1)
        b = np.zeros(z.shape[1])
        for _ in range(50):
            p = 1 / (1 + np.exp(-np.clip(z @ b, -30, 30)))
            step = np.linalg.solve((z * (w * p * (1 - p))[:, None]).T @ z + 1e-3 * np.eye(len(b)), z.T @ (w * (y - p)) - 1e-3 * b)
            b += step
            if abs(step).max() < 1e-9:
                break
        if b[1:].min() > 0:
            slopes = np.zeros(x.shape[1])
            slopes[used] = b[1:] / scale[used]
            return float(b[0]), *map(float, slopes)
        used.pop(int(np.argmin(b[1:])))  # a few texts can make it fall; a higher ratio never means a lower score
    mean = np.average(y, weights=w)
    return min(-1e-9, float(np.log(mean / (1 - mean)))), *[0.0] * x.shape[1]


def _merged(grams: np.ndarray, counts: np.ndarray):
    """Continuation counts one order down: how many expressions of each class end in each suffix."""
    keys, at = np.unique(grams >> K.U(8), return_inverse=True)
    return keys, np.stack([np.bincount(at, counts[:, c] > 0, len(keys)) for c in (0, 1)], axis=1)


def fit(docs: DataFrame, labels: DataFrame, fit_rows: int = FIT_ROWS, curve_rows: int = CURVE_ROWS) -> Model:
    """Count, smooth and calibrate; what the driver collects is bounded by the sample's expressions."""
    spark = docs.sparkSession
    sample = _sample(docs, labels, fit_rows, curve_rows)
    seen = _sorted_columns(_expressions(sample), "g")
    if not len(seen["g"]) or not seen["c0"].sum() or not seen["c1"].sum():
        return Model((np.zeros(0, K.U), np.ones(1)), [])
    grams, counts = seen["g"], np.stack([seen["c0"], seen["c1"]], axis=1)

    corpus = _sorted_columns(_shared_counts(docs), "g")
    keys, n = corpus["g"], corpus["n"].astype(float)
    _, at = np.unique(keys & K.U((1 << 8 * (SHARED - 1)) - 1), return_inverse=True)
    shared = (n + 1 / 256) / (np.bincount(at, n)[at] + 1)

    levels, k = [Level(ORDER, grams, counts, least=1)], ORDER
    while k > SHARED + 1:
        k -= 1
        grams, counts = _merged(grams, counts)
        levels.insert(0, Level(k, grams, counts))
    model = Model((keys, np.concatenate([shared, [1 / 256]]).astype(np.float32)), levels, _fit_words(docs, sample))

    held = spark.sparkContext.broadcast(model)

    def ratios(batches):
        pw = K.Powers()
        for batch in batches:
            for a, b in row_ranges(K.text_buffer(batch.column(1))[1], CHUNK):
                part = batch.slice(a, b - a)
                x = held.value.ratios(part.column(1), pw)
                yield pa.RecordBatch.from_arrays([pa.array(x[:, 0]), pa.array(x[:, 1]), part.column(0), part.column(2)], names=["x0", "x1", "y", "w"])

    seen = sample.where("curve").select("toxic", "text", "weight").mapInArrow(ratios, "x0 double, x1 double, y int, w double").toPandas()
    model.curve = _fit_curve(seen[["x0", "x1"]].to_numpy(float), seen["y"].to_numpy(float), seen["w"].to_numpy(float))
    return model


def _with_scores(docs: DataFrame, model: Model, keep: list[str]) -> DataFrame:
    """(row, score): the columns named, as a struct, so that no name of theirs can clash."""
    held = docs.sparkSession.sparkContext.broadcast(model)
    d = docs.select(F.struct(*[F.col(f"`{c}`") for c in keep]).alias("row"), F.col("text"))

    def run(batches):
        pw = K.Powers()
        for batch in batches:
            for a, b in row_ranges(K.text_buffer(batch.column(1))[1], CHUNK):
                part = batch.slice(a, b - a)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(held.value.scores(part.column(1), pw))], names=["row", "score"])

    from pyspark.sql.types import DoubleType, StructField, StructType

    return d.mapInArrow(run, StructType([d.schema["row"], StructField("score", DoubleType())]))


def score_toxicity(docs: DataFrame, labels: DataFrame, **bounds) -> DataFrame:
    """doc_id, held_out, score, predicted for each row of (doc_id, text)."""
    scored = _with_scores(docs, fit(docs, labels, **bounds), ["doc_id"]).select("row.doc_id", "score")
    return scored.select("doc_id", F.coalesce(fold("doc_id") == 0, F.lit(True)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def reject_toxic(docs: DataFrame, labels: DataFrame, threshold: float = 0.5, **bounds) -> DataFrame:
    """The rows, all columns, whose score is below the threshold."""
    return _with_scores(docs, fit(docs, labels, **bounds), docs.columns).where(F.col("score") < threshold).select("row.*")
