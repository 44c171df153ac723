"""Substring dedup over words: Rabin-Karp window hashes, counted in Spark, merged into removals.

Every window of `width` consecutive words of one document has a 64-bit fingerprint. Blocks of
documents send each distinct fingerprint once, by key range; a key that two blocks sent, or one
block holds twice, marks all its windows. Marked windows merge into maximal runs of words.
A fingerprint that is common to a third of all rows still crosses the shuffle once per block.

Defined results: null, empty or wordless text: 0 words, nothing removed, hash of no bytes; texts
shorter than a window: nothing removed; repeated rows: each row is a text of its own, so both are
removed; null ids are kept; no rows: no rows. Other columns are ignored.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from . import kernels as K
from .common import arrow_schema, n_blocks, pack_blocks, plan_bytes, unpack

KEYS_A_BUCKET = 1 << 21


def shared_keys(sent: DataFrame, buckets: int) -> DataFrame:
    """(bucket, block, keys) to (block, keys): the keys that another block sent too."""

    def meet(rows: pa.Table) -> pa.Table:
        blocks = rows.column("block").to_pylist()
        keys = [K.unpack_sorted(b.as_py()) for b in rows.column("keys")]
        twice = K.repeated(np.concatenate(keys)) if keys else np.zeros(0, K.U)
        out = [(b, K.pack_sorted(hit)) for b, k in zip(blocks, keys) if len(hit := k[K.isin_sorted(k, twice)])]
        return pa.table({"block": pa.array([b for b, _ in out], pa.int32()), "keys": pa.array([k for _, k in out], pa.binary())})

    return sent.repartition(buckets, "bucket").groupBy("bucket").applyInArrow(meet, "block int, keys binary")


def send(block: int, keys: np.ndarray, buckets: int) -> pa.Table:
    """The distinct keys of a block as one row for each bucket they fall into."""
    keys = np.unique(keys)
    cuts = K.bucket_cuts(keys, buckets)
    full = [b for b in range(buckets) if cuts[b + 1] > cuts[b]]
    return pa.table({"bucket": pa.array(full, pa.int32()), "block": pa.array([block] * len(full), pa.int32()), "keys": pa.array([K.pack_sorted(keys[cuts[b] : cuts[b + 1]]) for b in full], pa.binary())})


def answered(rows: pa.Table) -> np.ndarray:
    got = [K.unpack_sorted(b.as_py()) for b in rows.column("keys")]
    return np.sort(np.concatenate(got)) if got else np.zeros(0, K.U)


def _windows(texts, width: int, pw: K.Powers):
    """Spans and rows of the words, fingerprints of windows inside one row, and their first words."""
    buf, offsets = K.text_buffer(texts)
    starts, ends, rows = K.word_spans(buf, offsets, K.SPACE_WORD)
    prints = K.RangePrints(K.word_prints(buf, starts, ends, pw), pw).windows(width)
    at = np.flatnonzero(rows[width - 1 :] == rows[: len(rows) - width + 1]) if len(rows) >= width else np.zeros(0, np.int64)
    return buf, starts, ends, rows, prints[at], at


def remove_repeated_windows(docs: DataFrame, width: int = 35, with_text: bool = False) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 (and the kept text, if asked) for each row of (doc_id, text)."""
    docs = docs.select("doc_id", "text")
    blocks = n_blocks(docs)
    buckets = max(1, -(-2 * plan_bytes(docs) // (6 * KEYS_A_BUCKET)))
    parts = pack_blocks(docs, blocks)

    def emit(key: tuple[pa.Scalar, ...], rows: pa.Table) -> pa.Table:
        *_, prints, _ = _windows(unpack(rows).column("text"), width, K.Powers())
        return send(key[0].as_py(), prints, buckets)

    def finish(left: pa.Table, right: pa.Table) -> pa.Table:
        if not left.num_rows:
            return None
        table = unpack(left)
        buf, starts, ends, rows, prints, at = _windows(table.column("text"), width, K.Powers())
        hit = K.isin_sorted(prints, K.repeated(prints)) | K.isin_sorted(prints, answered(right))
        gone = K.cover(at[hit], at[hit] + width, len(starts))
        cuts = np.searchsorted(rows, np.arange(table.num_rows + 1))
        raw, n_removed, digests, kept_texts = buf.tobytes(), [], [], []
        for a, b in zip(cuts[:-1], cuts[1:]):
            g = gone[a:b]
            n_removed.append(int(g.sum()))
            kept = b" ".join(raw[s:e] for s, e in zip(starts[a:b][~g].tolist(), ends[a:b][~g].tolist()))
            digests.append(hashlib.sha256(kept).hexdigest())
            if with_text:
                kept_texts.append(kept.decode())
        out = {"doc_id": table.column("doc_id"), "n_words": pa.array(np.diff(cuts), pa.int64()), "n_removed": pa.array(n_removed, pa.int64()), "kept_sha256": pa.array(digests, pa.string())}
        return pa.table(out | ({"kept_text": pa.array(kept_texts, pa.string())} if with_text else {}))

    resp = shared_keys(parts.groupBy("block").applyInArrow(emit, "bucket int, block int, keys binary"), buckets)
    schema = f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, n_words long, n_removed long, kept_sha256 string"
    return parts.groupBy("block").cogroup(resp.groupBy("block")).applyInArrow(_never_none(finish, schema + ", kept_text string" * with_text), schema + ", kept_text string" * with_text)


def _never_none(fn, schema: str):
    """A cogroup without documents gives an empty table of the right type."""
    empty = arrow_schema(schema)

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        out = fn(left, right)
        return empty.empty_table() if out is None else out

    return run
