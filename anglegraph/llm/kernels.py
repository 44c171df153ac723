"""NumPy kernels over concatenated UTF-8 texts: word spans, fingerprints, window hashes.

Fingerprints are polynomial sums modulo 2^64 over two tables and two odd bases, mixed into
64 bits. Equal content has equal fingerprints wherever it stands.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

U = np.uint64
BASES = (0x9E3779B97F4A7C15, 0xD6E8FEB86659FD93)


def mix(x: np.ndarray) -> np.ndarray:
    """Murmur's 64-bit finalizer."""
    x = x ^ (x >> U(33))
    x *= U(0xFF51AFD7ED558CCD)
    x ^= x >> U(33)
    x *= U(0xC4CEB9FE1A85EC53)
    x ^= x >> U(33)
    return x


def byte_table(seed: int) -> np.ndarray:
    """A 64-bit value for each byte, from a counter through the finalizer."""
    return mix(np.arange(1, 257, dtype=U) * U(0x9E3779B97F4A7C15) + U(seed))


def powers(base: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    """base^0..n and their inverses modulo 2^64."""
    inverse = pow(base, -1, 1 << 64)
    with np.errstate(over="ignore"):
        up = np.full(n + 1, base, U)
        down = np.full(n + 1, inverse, U)
        up[0] = down[0] = 1
        return np.multiply.accumulate(up), np.multiply.accumulate(down)


class Powers:
    """Power tables, grown to the longest input seen so far."""

    def __init__(self):
        self.n, self.tables = 0, {}

    def get(self, base: int, n: int):
        if n > self.n:
            self.n, self.tables = max(n, 1 << 16), {}
        if base not in self.tables:
            self.tables[base] = powers(base, self.n)
        return self.tables[base]


def sums(values: np.ndarray, up: np.ndarray) -> np.ndarray:
    out = np.zeros(len(values) + 1, U)
    np.cumsum(values * up[: len(values)], out=out[1:])
    return out


class RangePrints:
    """Fingerprints of any ranges [a, b) of one sequence of 64-bit values."""

    def __init__(self, values: np.ndarray, pw: Powers, second: np.ndarray | None = None):
        other = values if second is None else second
        self.parts = []
        for base, seq in zip(BASES, (values, other)):
            up, down = pw.get(base, len(values) + 1)
            self.parts.append((sums(seq, up), down))

    def of(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        (s1, d1), (s2, d2) = self.parts
        h1 = (s1[b] - s1[a]) * d1[a]
        h2 = (s2[b] - s2[a]) * d2[a]
        return mix(h1 ^ mix(h2))

    def windows(self, n: int) -> np.ndarray:
        """Fingerprints of all length-n windows."""
        (s1, d1), (s2, d2) = self.parts
        m = len(s1) - n
        if m <= 0:
            return np.zeros(0, U)
        h1 = (s1[n:] - s1[:m]) * d1[:m]
        h2 = (s2[n:] - s2[:m]) * d2[:m]
        return mix(h1 ^ mix(h2))


def text_buffer(column) -> tuple[np.ndarray, np.ndarray]:
    """All bytes of a string column (null: empty) and the row offsets."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = pc.fill_null(pc.cast(column, pa.large_string()), "")
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if not len(column):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, offs, data = column.buffers()
    offsets = np.frombuffer(offs, np.int64)[column.offset : column.offset + len(column) + 1]
    raw = np.zeros(0, np.uint8) if data is None else np.frombuffer(data, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def _class(separators) -> np.ndarray:
    table = np.ones(256, bool)
    for a, b in separators:
        table[a : b + 1] = False
    return table


# The byte classes of the two word definitions.
SPACE_WORD = _class([(0x20, 0x20), (0x09, 0x0D)])
ALNUM_WORD = _class([(0x00, 0x2F), (0x3A, 0x60), (0x7B, 0x7F)])
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def word_spans(buf: np.ndarray, offsets: np.ndarray, table: np.ndarray):
    """Byte spans of the words and the row of each; words end where rows do."""
    if not len(buf):
        z = np.zeros(0, np.int64)
        return z, z, z
    inside = table[buf]
    full = offsets[:-1][offsets[1:] > offsets[:-1]]
    before = np.empty_like(inside)
    before[0] = False
    before[1:] = inside[:-1]
    before[full] = False
    starts = np.flatnonzero(inside & ~before)
    after = np.empty_like(inside)
    after[-1] = False
    after[:-1] = inside[1:]
    after[full[1:] - 1] = False
    ends = np.flatnonzero(inside & ~after) + 1
    rows = np.searchsorted(offsets, starts, "right") - 1
    return starts, ends, rows


def word_prints(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray, pw: Powers, step: int = 1 << 21) -> np.ndarray:
    """Fingerprints of the words; works through about `step` bytes at a time, however long a row is."""
    out = np.empty(len(starts), U)
    if not len(starts):
        return out
    cuts = np.unique(np.searchsorted(starts, np.arange(0, starts[-1] + step, step)))
    table = byte_table(7)
    for i, j in zip(cuts[:-1], [*cuts[1:-1], len(starts)]):
        base, last = starts[i], ends[j - 1]
        up, down = pw.get(BASES[0], int(last - base) + 1)
        s = sums(table[buf[base:last]], up)
        a, b = starts[i:j] - base, ends[i:j] - base
        out[i:j] = mix((s[b] - s[a]) * down[a] + (b - a).astype(U))
    return out


def cover(starts: np.ndarray, ends: np.ndarray, n: int) -> np.ndarray:
    """Boolean mask of positions inside any [start, end)."""
    delta = np.bincount(starts, minlength=n + 1).astype(np.int32)
    delta -= np.bincount(ends, minlength=n + 1).astype(np.int32)
    return np.cumsum(delta[:-1], dtype=np.int32) > 0


def isin_sorted(values: np.ndarray, table: np.ndarray) -> np.ndarray:
    if not len(table) or not len(values):
        return np.zeros(len(values), bool)
    at = np.searchsorted(table, values)
    at[at == len(table)] = 0
    return table[at] == values


def repeated(values: np.ndarray) -> np.ndarray:
    """Sorted values that occur more than once."""
    s = np.sort(values)
    return np.unique(s[1:][s[1:] == s[:-1]]) if len(s) > 1 else s[:0]


def pack_sorted(keys: np.ndarray) -> bytes:
    """Sorted 64-bit keys as counts by leading 16 bits and six low bytes each; short lists as they are."""
    import zstandard

    if len(keys) < 1 << 14:
        return b"\0\0\0\0" + keys.astype("<u8").tobytes()
    counts = np.bincount((keys >> U(48)).astype(np.int64), minlength=1 << 16).astype("<u4")
    low = keys.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :6]
    head = zstandard.compress(counts.tobytes(), 1)
    return len(head).to_bytes(4, "little") + head + low.tobytes()


def unpack_sorted(blob: bytes) -> np.ndarray:
    import zstandard

    n = int.from_bytes(blob[:4], "little")
    if not n:
        return np.frombuffer(blob, "<u8", offset=4).astype(U)
    counts = np.frombuffer(zstandard.decompress(blob[4 : 4 + n]), "<u4")
    low = np.frombuffer(blob, np.uint8, offset=4 + n).reshape(-1, 6)
    out = np.zeros((len(low), 8), np.uint8)
    out[:, :6] = low
    return out.view("<u8").ravel().astype(U) | (np.repeat(np.arange(1 << 16, dtype=U), counts) << U(48))


def bucket_cuts(keys: np.ndarray, buckets: int) -> np.ndarray:
    """Where each of `buckets` equal key ranges begins in sorted keys."""
    edges = np.array([(b << 64) // buckets for b in range(1, buckets)], U)
    return np.concatenate([[0], np.searchsorted(keys, edges), [len(keys)]]).astype(np.int64)
