"""Token counts by distinct pre-token, without ids.

A block of documents keeps, for each text, how often each unit occurs (a unit runs from one safe
space to the next and holds whole pre-tokens), and which pre-tokens each distinct unit has. Its
distinct pre-tokens go to the task of their hash, where the library cuts each distinct one of the
corpus into pieces once; the piece counts go back to the blocks that asked and are summed over the
frequencies. A pre-token in every document crosses the shuffle once per block.

Special strings inside a text count as the library counts them by default: one token each, and the
text on either side is cut apart.

Defined results: null or empty text: 0 bytes, 0 tokens; repeated rows count alike; null ids are
kept; no rows: no rows.
"""

from __future__ import annotations

import io
import re

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame

from .common import plan_bytes

BLOCK = 12 << 20


def _units(text: str, unsafe, cut, special) -> list[str]:
    """Units of a text, in order; special strings are units of their own."""
    if special and (parts := special.split(text))[1:]:
        return [u for p in parts if p for u in ([p] if special.fullmatch(p) else _units(p, unsafe, cut, None))]
    if unsafe.search(text) or text[0] == " " or text[-1] == " ":
        return cut.split(text)
    first, *rest = text.split(" ")
    return [first, *[" " + u for u in rest]]


def _zip(**arrays) -> bytes:
    import zstandard

    sink = io.BytesIO()
    np.savez(sink, **arrays)
    return zstandard.compress(sink.getvalue(), 5)


def _unzip(blob: bytes):
    import zstandard

    return np.load(io.BytesIO(zstandard.decompress(blob)), allow_pickle=False)


def _shrink(a: np.ndarray) -> np.ndarray:
    return a.astype(np.min_scalar_type(int(a.max()) if len(a) else 0))


def count_tokens(docs: DataFrame, tokenizer_file: str, limit: int = 1024) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit for each row of (doc_id, text)."""
    docs = docs.select("doc_id", "text")
    raw = docs.sparkSession.sparkContext.broadcast(open(tokenizer_file, encoding="utf-8").read())
    buckets = max(2, -(-2 * plan_bytes(docs) // (2 * BLOCK)))
    id_type = docs.schema["doc_id"].dataType.simpleString()

    def specials(tk):
        found = [t.content for t in tk.get_added_tokens_decoder().values()]
        return re.compile("(" + "|".join(map(re.escape, sorted(found, key=len, reverse=True))) + ")") if found else None

    def tally(batches):
        import xxhash
        import zstandard
        from tokenizers import Tokenizer

        tk = Tokenizer.from_str(raw.value)
        special = specials(tk)
        unsafe, cut = re.compile(r"\s\s"), re.compile(r"(?<=\S)(?= \S)")
        part, seq = TaskContext.get().partitionId(), 0
        ids, sizes, lens, units, counts, seen, nbytes = [], [], [], [], [], {}, 0

        def flush():
            nonlocal seq
            block = (part << 32) + seq
            seq += 1
            known: dict[str, int] = {}
            owner, pieces = [], []
            for u, k in seen.items():
                if special and special.fullmatch(u):
                    owner.append(k)
                    pieces.append(-1)
                    continue
                for p, _ in tk.pre_tokenizer.pre_tokenize_str(u):
                    owner.append(k)
                    pieces.append(known.setdefault(p, len(known)))
            to = np.array([xxhash.xxh64_intdigest(p) % buckets for p in known], np.int64)
            order = np.argsort(to, kind="stable")
            new = np.empty(len(order), np.int64)
            new[order] = np.arange(len(order))
            at = np.array(pieces, np.int64)
            at = np.where(at < 0, len(known), new[at]) if len(known) else np.zeros(len(at), np.int64)
            words = list(known)
            cuts = np.searchsorted(to[order], np.arange(buckets + 1))
            rows = []
            for b in range(buckets):
                if cuts[b + 1] > cuts[b]:
                    text = "\n".join(words[i] for i in order[cuts[b] : cuts[b + 1]].tolist())
                    rows.append((b, block, 0, zstandard.compress(text.encode(), 3)))
            uniq = [np.unique(np.array(u, np.int64), return_counts=True) for u in units]
            gaps = [np.diff(u, prepend=0) for u, _ in uniq]
            sink = io.BytesIO()
            table = pa.table({"doc_id": pa.concat_arrays(ids), "n_bytes": pa.array(sizes, pa.int64())})
            with pa.ipc.new_stream(sink, table.schema) as w:
                w.write_table(table)
            blob = _zip(rows=np.frombuffer(sink.getvalue(), np.uint8), n=np.array([len(u) for u, _ in uniq], np.int64), gap=_shrink(np.concatenate(gaps)), freq=_shrink(np.concatenate([c for _, c in uniq])), owner=_shrink(np.diff(np.array(owner, np.int64), prepend=0)), at=at.astype(np.uint32), known=np.array([len(known), len(seen)]))
            rows.append((-1 - seq - part * 4096, block, 1, blob))
            yield pa.RecordBatch.from_pydict({"route": pa.array([r[0] for r in rows], pa.int64()), "block": pa.array([r[1] for r in rows], pa.int64()), "kind": pa.array([r[2] for r in rows], pa.int32()), "blob": pa.array([r[3] for r in rows], pa.binary())})

        for batch in batches:
            for start in range(0, batch.num_rows, 512):
                piece = batch.slice(start, 512)
                ids.append(piece.column(0))
                for text in piece.column(1).to_pylist():
                    text = text or ""
                    size = len(text.encode())
                    sizes.append(size)
                    units.append([seen.setdefault(u, len(seen)) for u in _units(text, unsafe, cut, special)] if text else [])
                    nbytes += size
                if nbytes > BLOCK:
                    yield from flush()
                    ids, sizes, units, seen, nbytes = [], [], [], {}, 0
        if sizes:
            yield from flush()

    routed = docs.mapInArrow(tally, "route long, block long, kind int, blob binary")

    def cut_once(key: tuple[pa.Scalar, ...], rows: pa.Table) -> pa.Table:
        if key[0].as_py() < 0:
            return pa.table({"block": rows.column("block"), "bucket": pa.array([-1] * rows.num_rows, pa.int64()), "blob": rows.column("blob")})
        import zstandard
        from tokenizers import Tokenizer

        model = Tokenizer.from_str(raw.value).model
        n_pieces: dict[str, int] = {}
        out = []
        for row in rows.to_pylist():
            words = zstandard.decompress(row["blob"]).decode().split("\n")
            got = np.empty(len(words), np.int64)
            for i, w in enumerate(words):
                n = n_pieces.get(w)
                if n is None:
                    n = n_pieces[w] = len(model.tokenize(w))
                got[i] = n
            out.append((row["block"], key[0].as_py(), zstandard.compress(got.astype("<u4").tobytes(), 3)))
        return pa.table({"block": pa.array([o[0] for o in out], pa.int64()), "bucket": pa.array([o[1] for o in out], pa.int64()), "blob": pa.array([o[2] for o in out], pa.binary())})

    back = routed.groupBy("route").applyInArrow(cut_once, "block long, bucket long, blob binary")

    def total(rows: pa.Table) -> pa.Table:
        import zstandard

        got = sorted(rows.to_pylist(), key=lambda r: r["bucket"])
        held = _unzip(got[0]["blob"])
        counts = np.concatenate([np.frombuffer(zstandard.decompress(r["blob"]), "<u4") for r in got[1:]] + [np.ones(1, "<u4")]).astype(np.int64)
        n_known, n_units = held["known"].tolist()
        owner = np.cumsum(held["owner"].astype(np.int64))
        per_unit = np.bincount(owner, counts[held["at"]] if len(owner) else None, n_units)
        n = held["n"]
        doc = np.repeat(np.arange(len(n)), n)
        gap = held["gap"].astype(np.int64)
        run = np.cumsum(gap)
        begin = np.cumsum(n) - n
        base = np.zeros(len(n), np.int64)
        full = n > 0
        base[full] = run[begin[full]] - gap[begin[full]]
        unit = run - base[doc]
        tokens = np.bincount(doc, per_unit[unit] * held["freq"], len(n)).astype(np.int64) if len(unit) else np.zeros(len(n), np.int64)
        table = pa.ipc.open_stream(held["rows"].tobytes()).read_all()
        return pa.table({"doc_id": table.column("doc_id"), "n_bytes": table.column("n_bytes"), "n_tokens": pa.array(tokens, pa.int64()), "over_limit": pa.array(tokens > limit, pa.bool_())})

    return back.groupBy("block").applyInArrow(total, f"doc_id {id_type}, n_bytes long, n_tokens long, over_limit boolean")
