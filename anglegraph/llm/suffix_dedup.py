"""Exact repeated-substring removal by prefix-free parsing of the corpus.

Rolling-hash triggers cut every text into phrases. A suffix is ordered by a dictionary part (the
bytes up to its first trigger) and a parse part (what follows that trigger), as in a suffix array
made from a dictionary and a parse; only its first `width` bytes matter here. At corpus scale the
two parts are ordered by 64-bit names rather than by rank: equal prefixes are neighbours in either
order, and a name can be made in any task. Three steps, each counting names by key range:

1. the parse order: each trigger T sends the name of the bytes after it that every window first
   meeting T holds, with the name of all bytes of those windows. A parse name that occurs once
   rules all those windows out; if every whole name under it repeats, they are all in.
2. under the parse names left, and for windows without a trigger near their start, the dictionary
   part decides: windows are named one by one, in the undecided groups alone, and only those that
   hold no parse name that occurs once.
3. windows whose name repeats are removed; maximal removed runs are counted.

`block_suffix_order` gives the lexicographic order of one bounded text from the suffix arrays of its
dictionary and parse.

Defined results: null or empty text: 0 bytes, hash of no bytes; texts shorter than the width:
nothing removed; repeated rows are texts of their own and remove each other; bytes are judged on
the input, so the kept bytes may end inside a character; no rows: no rows.
"""

from __future__ import annotations

import hashlib
import io

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from . import kernels as K
from .common import arrow_schema, n_blocks, pack_blocks, plan_bytes, release, unpack, written
from .substring_dedup import KEYS_A_BUCKET, _never_none, answered, send, shared_keys

GRAM = 8  # bytes of a trigger
RARITY = 24  # one in so many places is a trigger
REACH = 136  # a window's first trigger counts if it starts within so many bytes
STEP = 1 << 21  # bytes named at a time
WHOLE_BYTES = 6  # of a whole name that are sent: it is compared under one 64-bit parse name only
LEVEL = 7  # zstd; texts cross the shuffle twice


def triggers(buf: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Positions whose next GRAM bytes lie in one row and hash to a trigger."""
    if len(buf) < GRAM:
        return np.zeros(0, np.int64)
    buf = np.ascontiguousarray(buf)
    found, n = [], len(buf) - GRAM + 1
    for a in range(0, n, STEP):
        grams = np.ndarray((min(STEP, n - a),), "<u8", buffer=buf.data, offset=a, strides=(1,))
        h = (grams ^ (grams >> K.U(29))) * K.U(0x9E3779B97F4A7C15)
        found.append(np.flatnonzero((h >> K.U(40)) % K.U(RARITY) == 0) + a)
    at = np.concatenate(found)
    row = np.searchsorted(offsets, at, "right") - 1
    return at[at + GRAM <= offsets[row + 1]]


def name_ranges(buf: np.ndarray, a: np.ndarray, b: np.ndarray, pw: K.Powers) -> np.ndarray:
    """Names of byte ranges [a, b), a ascending; works through about STEP bytes at a time."""
    out = np.empty(len(a), K.U)
    if not len(a):
        return out
    one, two = K.byte_table(11), K.byte_table(13)
    cuts = np.unique(np.searchsorted(a, np.arange(a[0], a[-1] + STEP, STEP)))
    for i, j in zip(cuts[:-1], [*cuts[1:-1], len(a)]):
        base, end = int(a[i]), int(b[i:j].max())
        piece = buf[base:end]
        out[i:j] = K.RangePrints(one[piece], pw, two[piece]).of(a[i:j] - base, b[i:j] - base)
    return out


class Parse:
    """The triggers of some texts, and the window starts that each one is first for."""

    def __init__(self, buf: np.ndarray, offsets: np.ndarray, width: int):
        self.buf, self.offsets, self.width = buf, offsets, width
        at = triggers(buf, offsets)
        row = np.searchsorted(offsets, at, "right") - 1
        before = np.concatenate([[-1], at[:-1]]) if len(at) else at
        low = np.maximum(np.maximum(before + 1, offsets[row]), at - REACH)
        high = np.minimum(at, offsets[row + 1] - width)
        # a trigger too near its text's end to be first in a window still has a parse name to count
        ok = at + width - REACH <= offsets[row + 1]
        self.at, self.low, self.high = at[ok], low[ok], high[ok]
        self.first = self.low <= self.high

    def names(self, pw: K.Powers) -> tuple[np.ndarray, np.ndarray]:
        """Parse and whole names; the whole name of a trigger that is first in no window is 0."""
        parse = name_ranges(self.buf, self.at, self.at + self.width - REACH, pw)
        whole = np.zeros(len(parse), K.U)
        low, high = self.low[self.first], self.high[self.first]
        shape = ((self.at[self.first] - low) * 4096 + (high - low)).astype(K.U)
        whole[self.first] = K.mix(name_ranges(self.buf, low, high + self.width, pw) + shape * K.U(0x9E3779B97F4A7C15)) | K.U(1)
        return parse, whole

    def far(self) -> np.ndarray:
        """Window starts with no trigger within reach."""
        n = len(self.buf)
        near = K.cover(self.low[self.first], self.high[self.first] + 1, n)
        lengths = np.diff(self.offsets)
        starts = self.offsets[:-1][lengths >= self.width]
        ends = self.offsets[1:][lengths >= self.width] - self.width + 1
        return np.flatnonzero(K.cover(starts, ends, n) & ~near)


def _expand(low: np.ndarray, high: np.ndarray) -> np.ndarray:
    """All positions of the inclusive ranges."""
    n = high - low + 1
    if not len(n):
        return np.zeros(0, np.int64)
    first = np.repeat(low - np.concatenate([[0], np.cumsum(n)[:-1]]), n)
    return first + np.arange(n.sum())


def _digest(table: pa.Table, buf, offsets, gone) -> dict:
    raw = np.diff(np.concatenate([[0], gone.view(np.int8), [0]])) if len(gone) else np.zeros(1, np.int8)
    n_removed, n_spans, digests = [], [], []
    for a, b in zip(offsets[:-1], offsets[1:]):
        g = gone[a:b]
        n_removed.append(int(g.sum()))
        n_spans.append(int((raw[a + 1 : b] == 1).sum()) + int(b > a and g[0]))
        digests.append(hashlib.sha256(buf[a:b][~g].tobytes() if n_removed[-1] else buf[a:b].tobytes()).hexdigest())
    return {"doc_id": table.column("doc_id"), "n_bytes": pa.array(np.diff(offsets), pa.int64()), "n_removed": pa.array(n_removed, pa.int64()), "n_spans": pa.array(n_spans, pa.int64()), "kept_sha256": pa.array(digests, pa.string())}


def _parse_order(sent: DataFrame, buckets: int) -> DataFrame:
    """(bucket, block, parse, whole) to (block, settled, open): the repeated parse names of each block."""

    def meet(rows: pa.Table) -> pa.Table:
        blocks = rows.column("block").to_pylist()
        parse = [K.unpack_sorted(b.as_py()) for b in rows.column("keys")]
        whole = [_widen(b.as_py()) for b in rows.column("whole")]
        p, w = np.concatenate(parse), np.concatenate(whole)
        order = np.lexsort((w, p))
        p, w = p[order], w[order]
        new_p = np.concatenate([[True], p[1:] != p[:-1]])
        new_w = np.concatenate([[True], (p[1:] != p[:-1]) | (w[1:] != w[:-1])])
        head_w = np.flatnonzero(new_w)
        alone = (np.diff(np.concatenate([head_w, [len(p)]])) == 1) & (w[head_w] != 0)
        head_p = np.flatnonzero(new_p)
        size = np.diff(np.concatenate([head_p, [len(p)]]))
        lone = np.add.reduceat(np.bincount(head_w, alone, len(p)), head_p)
        settled = p[head_p[(size > 1) & (lone == 0)]]
        undecided = p[head_p[(size > 1) & (lone > 0)]]
        out = []
        for b, k in zip(blocks, parse):
            k = np.unique(k)
            yes, may = k[K.isin_sorted(k, settled)], k[K.isin_sorted(k, undecided)]
            if len(yes) + len(may):
                out.append((b, K.pack_sorted(yes), K.pack_sorted(may)))
        return pa.table({"block": pa.array([x[0] for x in out], pa.int32()), "keys": pa.array([x[1] for x in out], pa.binary()), "may": pa.array([x[2] for x in out], pa.binary())})

    return sent.repartition(buckets, "bucket").groupBy("bucket").applyInArrow(meet, "block int, keys binary, may binary")


def _narrow(whole: np.ndarray) -> bytes:
    return whole.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :WHOLE_BYTES].tobytes()


def _widen(sent: bytes) -> np.ndarray:
    got = np.frombuffer(sent, np.uint8).reshape(-1, WHOLE_BYTES)
    return np.pad(got, ((0, 0), (0, 8 - WHOLE_BYTES))).view("<u8").ravel()


def _send_names(block: int, parse: np.ndarray, whole: np.ndarray, buckets: int) -> pa.Table:
    """Distinct name pairs, twice where a block holds a pair more than once."""
    order = np.lexsort((whole, parse))
    parse, whole = parse[order], whole[order]
    same = np.concatenate([[False], (parse[1:] == parse[:-1]) & (whole[1:] == whole[:-1])]) if len(parse) else np.zeros(0, bool)
    third = same & np.concatenate([[False], same[:-1]]) if len(parse) else same
    parse, whole = parse[~third], whole[~third]
    cuts = K.bucket_cuts(parse, buckets)
    full = [b for b in range(buckets) if cuts[b + 1] > cuts[b]]
    return pa.table({"bucket": pa.array(full, pa.int32()), "block": pa.array([block] * len(full), pa.int32()), "keys": pa.array([K.pack_sorted(parse[cuts[b] : cuts[b + 1]]) for b in full], pa.binary()), "whole": pa.array([_narrow(whole[cuts[b] : cuts[b + 1]]) for b in full], pa.binary())})


def remove_repeated_bytes(docs: DataFrame, width: int = 200) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 for each row of (doc_id, text)."""
    if width < REACH + GRAM:
        raise ValueError(f"width must be {REACH + GRAM} or more")
    docs = docs.select("doc_id", "text")
    blocks = n_blocks(docs)
    buckets = max(1, -(-2 * plan_bytes(docs) // (16 * KEYS_A_BUCKET)))
    parts = pack_blocks(docs, blocks, LEVEL)

    def emit(key: tuple[pa.Scalar, ...], rows: pa.Table) -> pa.Table:
        p = Parse(*K.text_buffer(unpack(rows).column("text")), width)
        return _send_names(key[0].as_py(), *p.names(K.Powers()), buckets)

    order = _parse_order(parts.groupBy("block").applyInArrow(emit, "bucket int, block int, keys binary, whole binary"), buckets)

    id_type = docs.schema["doc_id"].dataType.simpleString()
    digest = f"doc_id {id_type}, n_bytes long, n_removed long, n_spans long, kept_sha256 string"
    first = f"kind int, {digest}, bucket int, block int, keys binary"
    fields = arrow_schema(first)

    def settle(left: pa.Table, right: pa.Table) -> pa.Table:
        if not left.num_rows:
            return None
        table, block = unpack(left), left.column("block")[0].as_py()
        buf, offsets = K.text_buffer(table.column("text"))
        p, pw = Parse(buf, offsets, width), K.Powers()
        may = [K.unpack_sorted(b.as_py()) for b in right.column("may")]
        may = np.sort(np.concatenate(may)) if may else np.zeros(0, K.U)
        names = name_ranges(buf, p.at, p.at + width - REACH, pw)
        yes, ask = K.isin_sorted(names, answered(right)), K.isin_sorted(names, may)
        gone = K.cover(p.low[yes & p.first], p.high[yes & p.first] + width, len(buf))
        starts = np.sort(np.concatenate([_expand(p.low[ask & p.first], p.high[ask & p.first]), p.far()]))
        # a window holds the parse name of every trigger within reach; one that occurs once rules it out
        once = p.at[~(yes | ask)]
        starts = starts[np.searchsorted(once, starts) == np.searchsorted(once, starts + REACH, "right")]
        undecided = np.zeros(table.num_rows, bool)
        undecided[np.searchsorted(offsets, starts, "right") - 1] = True
        done = np.flatnonzero(~undecided)
        rest = np.flatnonzero(undecided)
        take = table.take(pa.array(done))
        out = [_rows(fields, {"kind": 0}, _digest(take, *_subset(buf, offsets, gone, done)))]
        if len(rest):
            keys = send(block, name_ranges(buf, starts, starts + width, pw), buckets)
            out.append(_rows(fields, {"kind": 1}, {n: keys.column(n) for n in keys.column_names}))
            new_buf, new_offsets, new_gone = _subset(buf, offsets, gone, rest)
            mark = np.zeros(len(buf), bool)
            mark[starts] = True
            mark = _subset(mark, offsets, gone, rest)[0]
            held = table.select(["doc_id"]).take(pa.array(rest))
            sink = io.BytesIO()
            np.savez(sink, buf=new_buf, offsets=new_offsets, gone=np.packbits(new_gone), ask=np.packbits(mark))
            ids = io.BytesIO()
            with pa.ipc.new_stream(ids, held.schema) as w:
                w.write_table(held)
            import zstandard

            blob = zstandard.compress(len(ids.getvalue()).to_bytes(8, "little") + ids.getvalue() + sink.getvalue(), LEVEL)
            out.append(_rows(fields, {"kind": 2}, {"block": pa.array([block], pa.int32()), "keys": pa.array([blob], pa.binary())}))
        return pa.concat_tables(out)

    step = written(parts.groupBy("block").cogroup(order.groupBy("block")).applyInArrow(_never_none(settle, first), first), "parse-order")
    del parts, order
    release(docs.sparkSession)

    def finish(left: pa.Table, right: pa.Table) -> pa.Table:
        if not left.num_rows:
            return None
        import zstandard

        blob = zstandard.decompress(left.column("keys")[0].as_py())
        n = int.from_bytes(blob[:8], "little")
        table = pa.ipc.open_stream(blob[8 : 8 + n]).read_all()
        held = np.load(io.BytesIO(blob[8 + n :]))
        buf, offsets = held["buf"], held["offsets"]
        gone = np.unpackbits(held["gone"], count=len(buf)).astype(bool)
        starts = np.flatnonzero(np.unpackbits(held["ask"], count=len(buf)))
        names = name_ranges(buf, starts, starts + width, K.Powers())
        hit = starts[K.isin_sorted(names, K.repeated(names)) | K.isin_sorted(names, answered(right))]
        return pa.table(_digest(table, buf, offsets, gone | K.cover(hit, hit + width, len(buf))))

    asked = shared_keys(step.where("kind = 1").select("bucket", "block", "keys"), buckets)
    rest = step.where("kind = 2").select("block", "keys").repartition(blocks, "block")
    late = rest.groupBy("block").cogroup(asked.groupBy("block")).applyInArrow(_never_none(finish, digest), digest)
    return step.where("kind = 0").select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256").unionByName(late)


def _subset(values: np.ndarray, offsets: np.ndarray, gone: np.ndarray, rows: np.ndarray):
    lengths = np.diff(offsets)[rows]
    at = _expand(offsets[rows][lengths > 0], offsets[rows + 1][lengths > 0] - 1)
    return values[at], np.concatenate([[0], np.cumsum(lengths)]), gone[at]


def _rows(schema: pa.Schema, constants: dict, columns: dict) -> pa.Table:
    """A table of the whole schema from some of its columns; the others are null."""
    n = len(next(iter(columns.values())))
    return pa.table([columns[f.name] if f.name in columns else pa.array([constants.get(f.name)] * n, f.type) for f in schema], schema=schema)


def block_suffix_order(data: bytes, gram: int = 4, rarity: int = 8) -> np.ndarray:
    """Suffix array of one bounded text, from the suffix arrays of its dictionary and its parse.

    Each suffix is keyed by its dictionary part (up to and with the next trigger) and the rank of
    the parse after it. Phrases overlap by a trigger, so no dictionary part is a proper prefix of
    another and the two keys together give the lexicographic order.
    """
    text = data + b"\0" * gram
    n = len(data)
    cut = [i for i in range(n + 1) if i == n or (i and int.from_bytes(text[i : i + gram], "little") * 0x9E3779B1 % (1 << 32) % rarity == 0)]
    phrases = [text[a : b + gram] for a, b in zip([0, *cut[:-1]], cut)]
    rank = {p: r for r, p in enumerate(sorted(set(phrases)))}
    parse = np.array([rank[p] for p in phrases] + [-1])
    order, size = np.unique(parse, return_inverse=True)[1], 1
    while size < len(parse):  # suffix array of the parse by doubling
        nxt = np.concatenate([order[size:], np.full(min(size, len(order)), -1)])
        pair = np.lexsort((nxt, order))
        fresh = np.concatenate([[0], (np.diff(order[pair]) != 0) | (np.diff(nxt[pair]) != 0)]).cumsum()
        order = np.empty_like(order)
        order[pair] = fresh
        size *= 2
    keys, start = [], 0
    for k, end in enumerate(cut):
        keys += [(text[i : end + gram], order[k + 1]) for i in range(start, end)]
        start = end
    return np.array(sorted(range(n), key=keys.__getitem__), np.int64)
