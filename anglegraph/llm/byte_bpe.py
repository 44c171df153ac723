"""Byte-level BPE encoding and decoding with the tiktoken library and a local rank file.

Long texts are cut at safe boundaries before they are encoded: between a character that is not
white space and a single space that such a character follows. No match of the split pattern spans
such a place, so the pieces' ids, one after the other, are the ids of the whole text. Decoding
joins the raw bytes of the ids and needs no valid UTF-8 on the way.

Defined results: null or empty text: no ids; a long text without a safe boundary is encoded as
one piece; repeated rows give repeated results; null ids of rows are kept; no rows: no rows. The
driver reads the rank file (a few MB, fixed by the vocabulary) and broadcasts its bytes.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

PIECE = 1 << 16


def ranks_of(raw: bytes) -> dict[bytes, int]:
    import base64

    return {base64.b64decode(a): int(b) for a, b in map(bytes.split, raw.splitlines()) if a}


def encoder(raw: bytes, pattern: str):
    import tiktoken

    return tiktoken.Encoding("local", pat_str=pattern, mergeable_ranks=ranks_of(raw), special_tokens={})


def safe_pieces(text: str, size: int = PIECE):
    """The text in pieces of `size` characters or more that end at safe boundaries."""
    import re

    cut, start = re.compile(r"(?<=\S)(?= \S)"), 0
    while len(text) - start > size:
        m = cut.search(text, start + size)
        if not m:
            break
        yield text[start : m.start()]
        start = m.start()
    yield text[start:] if start else text


def encode_text(enc, text: str | None) -> np.ndarray:
    if not text:
        return np.zeros(0, "<u4")
    if len(text) <= PIECE:
        return np.array(enc.encode_ordinary(text), "<u4")
    return np.concatenate([np.array(enc.encode_ordinary(p), "<u4") for p in safe_pieces(text)])


def _over_rows(docs: DataFrame, rank_file: str, pattern: str, columns: dict, make) -> DataFrame:
    """Each row with new columns; make(encoder, row as a dict) gives their values."""
    raw = docs.sparkSession.sparkContext.broadcast(open(rank_file, "rb").read())
    names = [c for c in docs.columns if c not in columns]
    schema = ", ".join([f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in names] + [f"{c} {t}" for c, t in columns.items()])

    def run(batches):
        enc = encoder(raw.value, pattern)
        for batch in batches:
            for start in range(0, batch.num_rows, 256):
                part = batch.slice(start, 256)
                made = [make(enc, row) for row in part.to_pylist()]
                keep = [part.column(batch.schema.get_field_index(c)) for c in names]
                new = [pa.array([m[i] for m in made], _ARROW[t]) for i, t in enumerate(columns.values())]
                yield pa.RecordBatch.from_arrays(keep + new, names=names + list(columns))

    return docs.mapInArrow(run, schema)


_ARROW = {"long": pa.int64(), "string": pa.string(), "array<int>": pa.list_(pa.int32()), "binary": pa.binary()}


def encode(docs: DataFrame, rank_file: str, pattern: str) -> DataFrame:
    """The rows with `ids`: the token ids of `text`."""
    return _over_rows(docs, rank_file, pattern, {"ids": "array<int>"}, lambda enc, r: (encode_text(enc, r["text"]).astype(int).tolist(),))


def decode(encoded: DataFrame, rank_file: str, pattern: str) -> DataFrame:
    """The rows with `decoded`: the raw bytes of `ids` (null: no bytes)."""
    return _over_rows(encoded, rank_file, pattern, {"decoded": "binary"}, lambda enc, r: (enc.decode_bytes(r["ids"] or []),))


def round_trip(docs: DataFrame, rank_file: str, pattern: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256: each text encoded, then decoded from its ids."""

    def make(enc, row):
        ids = encode_text(enc, row["text"])
        raw = enc.decode_bytes(ids.tolist())
        return len(ids), hashlib.sha256(ids.tobytes()).hexdigest(), hashlib.sha256(raw).hexdigest()

    out = _over_rows(docs.select("doc_id", "text"), rank_file, pattern, {"n_tokens": "long", "ids_sha256": "string", "decoded_sha256": "string"}, make)
    return out.drop("text")
