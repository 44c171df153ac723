"""Benchmark decontamination by a broadcast hash set of normalised test n-grams.

Items are cut into windows of `width` words (a shorter item is one window) and kept as sorted
64-bit window fingerprints with the fingerprints of their words. The items are few: up to
ITEM_BYTES of them go out as one broadcast; more go out in slices of that size, which each batch of
documents meets one after the other, so memory stays bounded. A fingerprint hit is verified word by
word before it counts.

Defined results: null or wordless text: no words, no hits, clean; items without words match
nothing; repeated items each count; repeated rows give repeated results; an empty benchmark finds
nothing; no rows: no rows. `filter_contaminated` keeps every column as it is.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kernels as K

ITEM_BYTES = 64 << 20


class Items:
    """Window tables of some items: for each window length, sorted fingerprints and their places."""

    def __init__(self, ids: list, texts: list, width: int):
        self.ids = ids
        buf, offsets = K.text_buffer(pa.array(texts, pa.string()))
        low = K.LOWER[buf]
        starts, ends, rows = K.word_spans(low, offsets, K.ALNUM_WORD)
        pw = K.Powers()
        self.words = K.word_prints(low, starts, ends, pw)
        prints = K.RangePrints(self.words, pw)
        first = np.searchsorted(rows, np.arange(len(ids)))
        count = np.bincount(rows, minlength=len(ids))
        self.tables = {}
        for n in sorted({min(int(c), width) for c in count if c}):
            owners = np.flatnonzero(count >= width) if n == width else np.flatnonzero(count == n)
            at = np.concatenate([first[o] + np.arange(count[o] - n + 1) for o in owners])
            item = np.repeat(owners, count[owners] - n + 1)
            key = prints.of(at, at + n)
            order = np.argsort(key, kind="stable")
            self.tables[n] = key[order], at[order], item[order]


def _slices(benchmark: DataFrame, width: int) -> list[Items]:
    """The items in slices of bounded bytes; rows arrive on the driver one partition at a time."""
    out, ids, texts, size = [], [], [], 0
    for row in benchmark.select(F.col("item_id").cast("string").alias("item_id"), "text").toLocalIterator():
        ids.append(row["item_id"] or "")
        texts.append(row["text"] or "")
        size += len(texts[-1])
        if size > ITEM_BYTES:
            out.append(Items(ids, texts, width))
            ids, texts, size = [], [], 0
    return out + ([Items(ids, texts, width)] if ids else [])


def _scan(texts, slices, pw: K.Powers):
    """Word counts, hit counts and the items met, by row; the word spans and the hit mask."""
    buf, offsets = K.text_buffer(texts)
    low = K.LOWER[buf]
    starts, ends, rows = K.word_spans(low, offsets, K.ALNUM_WORD)
    words = K.word_prints(low, starts, ends, pw)
    prints = K.RangePrints(words, pw)
    hit = np.zeros(len(words), bool)
    met: list[set] = [set() for _ in range(len(offsets) - 1)]
    for s in slices:
        items = s.value
        for n, (keys, at, item) in items.tables.items():
            found = prints.windows(n)
            here = np.flatnonzero(K.isin_sorted(found, keys))
            here = here[rows[here] == rows[here + n - 1]]
            left = np.searchsorted(keys, found[here], "left")
            many = np.searchsorted(keys, found[here], "right") - left
            place = np.repeat(here, many)
            entry = np.repeat(left - (np.cumsum(many) - many), many) + np.arange(many.sum())
            true = np.ones(len(place), bool)
            for k in range(n):
                true &= words[place + k] == items.words[at[entry] + k]
            place, entry = place[true], entry[true]
            hit |= K.cover(place, place + n, len(words))
            pairs = np.unique(np.stack([rows[place], item[entry]]), axis=1) if len(place) else np.zeros((2, 0), int)
            for r, i in pairs.T.tolist():
                met[r].add((s.id, i, items.ids[i]))
        if len(slices) > 1:
            s.forget()
    n_words = np.bincount(rows, minlength=len(met))
    n_hit = np.bincount(rows, hit, len(met)).astype(np.int64)
    return n_words, n_hit, met, (buf, starts, ends, rows, hit)


class _Slice:
    def __init__(self, broadcast, number: int):
        self.broadcast, self.id = broadcast, number

    @property
    def value(self) -> Items:
        return self.broadcast.value

    def forget(self) -> None:
        self.broadcast.__dict__.pop("_value", None)


def _sent(docs: DataFrame, benchmark: DataFrame, width: int) -> list[_Slice]:
    sc = docs.sparkSession.sparkContext
    return [_Slice(sc.broadcast(x), i) for i, x in enumerate(_slices(benchmark, width))]


def contamination(docs: DataFrame, benchmark: DataFrame, width: int = 13, share: int = 20) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated for each row of (doc_id, text)."""
    docs = docs.select("doc_id", "text")
    slices = _sent(docs, benchmark, width)

    def run(batches):
        pw = K.Powers()
        for batch in batches:
            for a in range(0, batch.num_rows, 1024):
                part = batch.slice(a, 1024)
                n_words, n_hit, met, _ = _scan(part.column(1), slices, pw)
                shas = [hashlib.sha256(",".join(sorted(x[2] for x in m)).encode()).hexdigest() for m in met]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(n_words, pa.int64()), pa.array(n_hit, pa.int64()), pa.array([len(m) for m in met], pa.int64()), pa.array(shas, pa.string()), pa.array((n_hit > 0) & (share * n_hit >= n_words), pa.bool_())], names=["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated"])

    return docs.mapInArrow(run, f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean")


def filter_contaminated(docs: DataFrame, benchmark: DataFrame, width: int = 13, share: int = 20, mode: str = "drop") -> DataFrame:
    """The rows, all columns, without contaminated documents ('drop') or with hit spans cut out ('cut')."""
    if mode not in ("drop", "cut"):
        raise ValueError("mode is 'drop' or 'cut'")
    slices = _sent(docs, benchmark, width)
    place = docs.columns.index("text")

    def run(batches):
        pw = K.Powers()
        for batch in batches:
            for a in range(0, batch.num_rows, 1024):
                part = batch.slice(a, 1024)
                n_words, n_hit, _, (buf, starts, ends, rows, hit) = _scan(part.column(place), slices, pw)
                if mode == "drop":
                    yield part.filter(pa.array(~((n_hit > 0) & (share * n_hit >= n_words)), pa.bool_()))
                    continue
                texts = part.column(place).to_pylist()
                for r in np.flatnonzero(n_hit).tolist():
                    lo, hi = np.searchsorted(rows, [r, r + 1])
                    base = np.searchsorted(rows, r)
                    first = K.text_buffer(part.column(place).slice(0, r + 1))[1][-2] if r else 0
                    raw, out, last = texts[r].encode(), [], 0
                    for k in range(lo, hi):
                        if hit[k] and (k == base or not hit[k - 1]):
                            out.append(raw[last : starts[k] - first])
                        if hit[k]:
                            last = ends[k] - first
                    texts[r] = b"".join([*out, raw[last:]]).decode()
                arrays = [pa.array(texts, pa.string()) if i == place else part.column(i) for i in range(part.num_columns)]
                yield pa.RecordBatch.from_arrays(arrays, schema=part.schema)

    return docs.mapInArrow(run, docs.schema)
