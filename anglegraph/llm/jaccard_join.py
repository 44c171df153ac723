"""Exact n-gram Jaccard join with signature trees.

Documents are sets of distinct word shingles. Equal sets are one class, with one set to compare.

1. Sieve. In one global order (by fingerprint) two sets of similarity 0.8 or more share at least
   l tokens of their first n - ceil(0.8 n) + l ones, for any l that both use. Blocks send these
   prefixes by key range; a set with fewer prefix tokens that occur elsewhere than its partners
   would need is linked with nothing and ends here, before its whole set moves.
2. Regions. Over the sets left every token's document frequency is counted, the sieve is repeated
   with whole sets, and sets that share a token of their rarest n - ceil(0.8 n) + 1 are tied to the
   smallest set of that token. Linked sets are in one connected region of these ties.
3. Trees. Each region is joined on its own. A tree node has the OR of its sets' token bitmaps, their
   range of sizes and the most tokens that one of them loses to shared bits. Two trees are walked
   together; a pair of nodes goes on only if its largest possible overlap can reach the threshold.
   Leaf pairs not yet connected are verified on the sets. Regions of more than CHUNK sets are dealt
   in chunks, and each pair of chunks is a task of its own.

Only sets, prefixes and one tie for each token and set move; no group is expanded into all pairs,
and a class of copies counts once.

Defined results: null, empty or wordless text: an empty set, linked with nothing; fewer words than a
shingle: the whole sequence is the one shingle; repeated rows form a class; null ids are never
smallest unless alone; no rows: no rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kernels as K
from .common import n_blocks, pack_blocks, plan_bytes, release, unpack, written
from .components import connected_components
from .substring_dedup import KEYS_A_BUCKET, answered, send, shared_keys

CHUNK = 1024
FAN = 8
SET_BYTES = 16 << 20  # of sets in a block of step 2


def least_overlap(n):
    """ceil(0.8 n): tokens that a linked set of n tokens shares."""
    return (4 * n + 4) // 5


def spare(n):
    """l of the sieve: ceil(0.2 n)."""
    return (n + 4) // 5


def shingle_sets(texts, width: int, pw: K.Powers):
    """All sets, one after the other and each sorted, with the bounds of each row's set."""
    buf, offsets = K.text_buffer(texts)
    low = K.LOWER[buf]
    starts, ends, rows = K.word_spans(low, offsets, K.SPACE_WORD)
    n_rows = len(offsets) - 1
    prints = K.RangePrints(K.word_prints(low, starts, ends, pw), pw)
    cuts = np.searchsorted(rows, np.arange(n_rows + 1))
    count = np.diff(cuts)
    at = np.flatnonzero(rows[width - 1 :] == rows[: len(rows) - width + 1]) if len(rows) >= width else np.zeros(0, np.int64)
    few = np.flatnonzero((count > 0) & (count < width))
    tokens = np.concatenate([prints.windows(width)[at], prints.of(cuts[few], cuts[few + 1])])
    owner = np.concatenate([rows[at], few])
    order = np.lexsort((tokens, owner))
    tokens, owner = tokens[order], owner[order]
    new = np.ones(len(tokens), bool)
    new[1:] = (tokens[1:] != tokens[:-1]) | (owner[1:] != owner[:-1])
    tokens, owner = tokens[new], owner[new]
    return tokens, np.searchsorted(owner, np.arange(n_rows + 1))


def set_print(tokens: np.ndarray, cuts: np.ndarray) -> np.ndarray:
    """A fingerprint of each set, without regard to order."""
    a, b = K.mix(tokens + K.U(1)), K.mix(tokens ^ K.U(0xD6E8FEB86659FD93))
    total = lambda x: np.diff(np.concatenate([np.zeros(1, K.U), np.cumsum(x)])[cuts])
    return K.mix(total(a) ^ K.mix(total(b) + np.diff(cuts).astype(K.U)))


def _prefix(tokens, cuts):
    """Whether each token is in the sieve's prefix of its set, and each token's set."""
    n = np.diff(cuts)
    row = np.repeat(np.arange(len(n)), n)
    rank = np.arange(len(tokens)) - cuts[row]
    return rank < np.minimum(n, n - least_overlap(n) + spare(n))[row], row


class Tree:
    """Sets as leaves in order; levels of nodes above them."""

    def __init__(self, sets: list[np.ndarray], bits: int):
        self.sets = sets
        size = np.array([len(s) for s in sets])
        maps = np.zeros((len(sets), bits // 8), np.uint8)
        row = np.repeat(np.arange(len(sets)), size)
        bit = (np.concatenate(sets) >> K.U(20)).astype(np.int64) % bits
        np.bitwise_or.at(maps, (row, bit >> 3), (1 << (bit & 7)).astype(np.uint8))
        maps = maps.view(K.U)
        lost = size - np.bitwise_count(maps).sum(axis=1, dtype=np.int64)
        self.levels = [(maps, size, size, lost)]
        while len(self.levels[-1][0]) > 1:
            maps, low, high, lost = self.levels[-1]
            at = np.arange(0, len(maps), FAN)
            self.levels.append((np.bitwise_or.reduceat(maps, at), np.minimum.reduceat(low, at), np.maximum.reduceat(high, at), np.maximum.reduceat(lost, at)))


def _may_link(one, two, a, b, leaves: bool):
    """Which node pairs can hold a linked pair."""
    (maps1, low1, high1, lost1), (maps2, low2, high2, lost2) = one, two
    ok = (5 * high1[a] >= 4 * low2[b]) & (5 * high2[b] >= 4 * low1[a])
    a, b = a[ok], b[ok]
    common = np.bitwise_count(maps1[a] & maps2[b]).sum(axis=1, dtype=np.int64)
    most = np.minimum(np.minimum(high1[a], high2[b]), common + np.minimum(lost1[a], lost2[b]))
    fits = 180 * most >= 80 * (low1[a] + low2[b]) if leaves else 5 * most >= 4 * np.maximum(low1[a], low2[b])
    return a[fits], b[fits]


def dual_walk(one: Tree, two: Tree, same: bool, step: int = 1 << 13):
    """Leaf pairs that the bounds leave, in batches; for one tree with itself each pair once."""
    top = max(len(one.levels), len(two.levels)) - 1
    stack = [(top, np.zeros(1, np.int64), np.zeros(1, np.int64))]
    level = lambda t, k: t.levels[min(k, len(t.levels) - 1)]
    while stack:
        k, a, b = stack.pop()
        if len(a) > step:
            stack += [(k, a[i : i + step], b[i : i + step]) for i in range(0, len(a), step)]
            continue
        a, b = _may_link(level(one, k), level(two, k), a, b, k == 0)
        if k == 0:
            if same:
                a, b = a[a < b], b[a < b]
            if len(a):
                yield a, b
            continue
        na, nb = len(level(one, k - 1)[0]), len(level(two, k - 1)[0])
        kids = lambda x, t: x[:, None] * FAN + np.arange(FAN) if k < len(t.levels) else x[:, None]
        ca, cb = kids(a, one), kids(b, two)
        pa_, pb = np.repeat(ca, cb.shape[1], axis=1).ravel(), np.tile(cb, (1, ca.shape[1])).ravel()
        ok = (pa_ < na) & (pb < nb) & ((pa_ <= pb) if same else True)
        stack.append((k - 1, pa_[ok], pb[ok]))


def link_sets(left: list[np.ndarray], right: list[np.ndarray] | None = None) -> list[tuple[int, int]]:
    """Links (i, j) that span the groups of linked sets; j counts on after `left` where `right` is given."""

    def ordered(sets):
        key = [(int(np.log(max(1, len(s))) / np.log(1.25)), int(s[0])) for s in sets]
        return sorted(range(len(sets)), key=key.__getitem__)

    most = max(len(s) for s in left + (right or []))
    bits = 1 << min(16, max(9, int(4 * most).bit_length()))
    o1 = ordered(left)
    one = Tree([left[i] for i in o1], bits)
    o2 = ordered(right) if right is not None else o1
    two = Tree([right[i] for i in o2], bits) if right is not None else one
    shift = len(left) if right is not None else 0
    root = np.arange(len(left) + (len(right) if right is not None else 0))

    def find(i):
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    out = []
    for a, b in dual_walk(one, two, right is None):
        for i, j in zip(a.tolist(), b.tolist()):
            x, y = o1[i], o2[j] + shift
            if (rx := find(x)) == (ry := find(y)):
                continue
            s, t = one.sets[i], two.sets[j]
            both = int(K.isin_sorted(s, t).sum())
            if 100 * both >= 80 * (len(s) + len(t) - both):
                root[max(rx, ry)] = min(rx, ry)
                out.append((x, y))
    return out


def _sieved(docs: DataFrame, width: int) -> DataFrame:
    """(doc_id, n, fp, tokens): fp for sets that pass the sieve, tokens once for each fp and block."""
    blocks = n_blocks(docs)
    buckets = max(1, -(-2 * plan_bytes(docs) // (12 * KEYS_A_BUCKET)))
    parts = pack_blocks(docs, blocks)

    def emit(key: tuple[pa.Scalar, ...], rows: pa.Table) -> pa.Table:
        tokens, cuts = shingle_sets(unpack(rows).column("text"), width, K.Powers())
        return send(key[0].as_py(), tokens[_prefix(tokens, cuts)[0]], buckets)

    empty = pa.schema([("doc_id", pa.int64()), ("n", pa.int64()), ("fp", pa.int64()), ("tokens", pa.binary())])

    def finish(left: pa.Table, right: pa.Table) -> pa.Table:
        if not left.num_rows:
            return empty.empty_table()
        table = unpack(left)
        tokens, cuts = shingle_sets(table.column("text"), width, K.Powers())
        head, row = _prefix(tokens, cuts)
        own = tokens[head]
        seen = K.isin_sorted(own, K.repeated(own)) | K.isin_sorted(own, answered(right))
        n = np.diff(cuts)
        shared = np.bincount(row[head], seen, len(n)).astype(np.int64)
        passed = (n > 0) & (shared >= spare(least_overlap(n)))
        fp = set_print(tokens, cuts)
        first = np.zeros(len(n), bool)
        some = np.flatnonzero(passed)
        first[some[np.unique(fp[some], return_index=True)[1]]] = True
        sets = [tokens[cuts[i] : cuts[i + 1]].astype("<u8").tobytes() if first[i] else None for i in range(len(n))]
        return pa.table({"doc_id": table.column("doc_id").cast(pa.int64()), "n": pa.array(n, pa.int64()), "fp": pa.array(fp.view(np.int64), pa.int64(), mask=~passed), "tokens": pa.array(sets, pa.binary())})

    resp = shared_keys(parts.groupBy("block").applyInArrow(emit, "bucket int, block int, keys binary"), buckets)
    return written(parts.groupBy("block").cogroup(resp.groupBy("block")).applyInArrow(finish, "doc_id long, n long, fp long, tokens binary"), "jaccard-sieve")


def _tables(rows: pa.Table):
    """The distinct sets of a block: fingerprints, tokens and bounds."""
    fp = rows.column("fp").to_numpy()
    fps, first = np.unique(fp, return_index=True)
    held = rows.column("tokens")
    sets = [np.frombuffer(held[int(i)].as_py(), "<u8") for i in first]
    return fps, np.concatenate(sets), np.concatenate([[0], np.cumsum([len(s) for s in sets])])


def _regions(rows: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(fp, n, tokens) of the sets that pass the second sieve, and their ties (a, b)."""
    sets = rows.where("tokens is not null").select("fp", "tokens")
    size = sets.agg(F.sum(F.length("tokens"))).first()[0] or 0
    blocks = max(1, -(-size // SET_BYTES))
    buckets = max(1, -(-size // (8 * KEYS_A_BUCKET)))
    dealt = sets.withColumn("block", F.pmod(F.xxhash64("fp"), F.lit(blocks)).cast("int")).repartition(blocks, "block")

    def emit(key: tuple[pa.Scalar, ...], part: pa.Table) -> pa.Table:
        keys, n = np.unique(_tables(part)[1], return_counts=True)
        cuts = K.bucket_cuts(keys, buckets)
        full = [b for b in range(buckets) if cuts[b + 1] > cuts[b]]
        return pa.table({"bucket": pa.array(full, pa.int32()), "block": pa.array([key[0].as_py()] * len(full), pa.int32()), "keys": pa.array([K.pack_sorted(keys[cuts[b] : cuts[b + 1]]) for b in full], pa.binary()), "df": pa.array([n[cuts[b] : cuts[b + 1]].astype("<u4").tobytes() for b in full], pa.binary())})

    def meet(part: pa.Table) -> pa.Table:
        keys = [K.unpack_sorted(x.as_py()) for x in part.column("keys")]
        n = [np.frombuffer(x.as_py(), "<u4") for x in part.column("df")]
        every, at = np.unique(np.concatenate(keys), return_inverse=True)
        total = np.bincount(at, np.concatenate(n), len(every)).astype(np.int64)
        out = []
        for b, k in zip(part.column("block").to_pylist(), keys):
            df = total[np.searchsorted(every, k)]
            out.append((b, K.pack_sorted(k[df > 1]), np.minimum(df[df > 1], 0xFFFFFFFF).astype("<u4").tobytes()))
        return pa.table({"block": pa.array([o[0] for o in out], pa.int32()), "keys": pa.array([o[1] for o in out], pa.binary()), "df": pa.array([o[2] for o in out], pa.binary())})

    empty = pa.schema([("fp", pa.int64()), ("n", pa.int64()), ("tokens", pa.binary()), ("head", pa.list_(pa.int64()))])

    def finish(left: pa.Table, right: pa.Table) -> pa.Table:
        if not left.num_rows:
            return empty.empty_table()
        fps, tokens, cuts = _tables(left)
        keys = [K.unpack_sorted(x.as_py()) for x in right.column("keys")]
        n_df = [np.frombuffer(x.as_py(), "<u4") for x in right.column("df")]
        keys = np.concatenate(keys) if keys else np.zeros(0, K.U)
        order = np.argsort(keys)
        keys, counts = keys[order], (np.concatenate(n_df) if n_df else np.zeros(0, "<u4")).astype(np.int64)[order]
        df = np.ones(len(tokens), np.int64)
        hit = K.isin_sorted(tokens, keys)
        df[hit] = counts[np.searchsorted(keys, tokens[hit])]
        n = np.diff(cuts)
        row = np.repeat(np.arange(len(n)), n)
        stay = np.bincount(row, df > 1, len(n)) >= least_overlap(n)
        order = np.lexsort((tokens, df, row))
        rank = np.arange(len(tokens)) - cuts[row]
        rare = (rank < (n - least_overlap(n) + 1)[row]) & (df[order] > 1)
        heads = tokens[order][rare].view(np.int64)
        ends = np.searchsorted(row[rare], np.arange(len(n) + 1))
        some = np.flatnonzero(stay)
        return pa.table({"fp": pa.array(fps[some], pa.int64()), "n": pa.array(n[some], pa.int64()), "tokens": pa.array([tokens[cuts[i] : cuts[i + 1]].tobytes() for i in some], pa.binary()), "head": pa.array([heads[ends[i] : ends[i + 1]] for i in some], pa.list_(pa.int64()))})

    counted = dealt.groupBy("block").applyInArrow(emit, "bucket int, block int, keys binary, df binary")
    back = counted.repartition(buckets, "bucket").groupBy("bucket").applyInArrow(meet, "block int, keys binary, df binary")
    left = written(dealt.groupBy("block").cogroup(back.groupBy("block")).applyInArrow(finish, "fp long, n long, tokens binary, head array<long>"), "jaccard-sets")
    heads = left.select("fp", F.explode("head").alias("token"))
    lead = heads.groupBy("token").agg(F.min("fp").alias("a"), F.max("fp").alias("z")).where("a <> z").select("token", "a")
    ties = heads.join(lead, "token").where("a <> fp").select("a", F.col("fp").alias("b"))
    return left.select("fp", "n", "tokens"), ties


def _links(sets: DataFrame, region: DataFrame) -> DataFrame:
    """(a, b): verified links that span each region's groups."""
    sized = region.groupBy("component").agg(F.count("*").alias("size"))
    placed = region.join(sized, "component").select(F.col("node").alias("fp"), "component", "size")
    d = sets.join(placed, "fp")
    chunks = F.ceil(F.col("size") / CHUNK).cast("int")
    d = d.withColumn("mine", F.pmod(F.xxhash64("fp", F.lit(3)), chunks).cast("int"))
    d = d.withColumn("other", F.explode(F.sequence(F.lit(0), chunks - 1)))
    d = d.withColumn("i", F.least("mine", "other")).withColumn("j", F.greatest("mine", "other"))
    # small regions share tasks, by a hash; a pair of chunks of a large one has its own
    packs = F.lit(256)
    d = d.withColumn("task", F.when(F.col("size") > CHUNK // 4, F.xxhash64("component", "i", "j")).otherwise(F.pmod(F.xxhash64("component"), packs)))

    def join(rows: pa.Table) -> pa.Table:
        comp, i, j, mine = (rows.column(c).to_numpy() for c in ("component", "i", "j", "mine"))
        fp = rows.column("fp").to_numpy()
        held = rows.column("tokens")
        order = np.lexsort((fp, mine, j, i, comp))
        same = np.ones(len(order), bool)
        same[1:] = False
        for x in (comp, i, j):
            same[1:] |= x[order][1:] != x[order][:-1]
        cuts = [*np.flatnonzero(same).tolist(), len(order)]
        out = []
        for p, q in zip(cuts, cuts[1:]):
            at = order[p:q]
            get = lambda x: [np.frombuffer(held[int(r)].as_py(), "<u8") for r in x]
            if i[at[0]] == j[at[0]]:
                left, right = at, None
            else:
                left, right = at[mine[at] == i[at[0]]], at[mine[at] == j[at[0]]]
            if len(left) and (right is None or len(right)):
                ids = fp[left if right is None else np.concatenate([left, right])]
                out += [(ids[x], ids[y]) for x, y in link_sets(get(left), None if right is None else get(right))]
        return pa.table({"a": pa.array([o[0] for o in out], pa.int64()), "b": pa.array([o[1] for o in out], pa.int64())})

    return d.select("task", "component", "i", "j", "mine", "fp", "tokens").groupBy("task").applyInArrow(join, "a long, b long")


def join_documents(docs: DataFrame, width: int = 5) -> DataFrame:
    """doc_id, n_shingles, component_id for each row of (doc_id, text)."""
    rows = _sieved(docs.select("doc_id", "text"), width)
    release(docs.sparkSession)
    sets, ties = _regions(rows)
    region = connected_components(ties)
    groups = connected_components(_links(sets, region)).select(F.col("node").alias("fp"), "component")
    least = rows.where("fp is not null").groupBy("fp").agg(F.min("doc_id").alias("least"))
    named = least.join(groups, "fp", "left").withColumn("component", F.coalesce("component", "fp"))
    ids = named.groupBy("component").agg(F.min("least").alias("component_id"))
    named = named.join(ids, "component").select("fp", "component_id")
    out = rows.select("doc_id", "n", "fp").join(named, "fp", "left")
    return out.select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("component_id", "doc_id").alias("component_id"))


def keep_one(docs: DataFrame, width: int = 5) -> DataFrame:
    """The rows, all columns, of one document in each group: the one with the smallest id."""
    from pyspark.sql import Window

    kept = join_documents(docs, width).where("doc_id <=> component_id").select(F.col("doc_id").alias("_id")).distinct()
    d = docs.join(kept, F.col("doc_id").eqNullSafe(F.col("_id")), "left_semi")
    w = Window.partitionBy("doc_id").orderBy(F.xxhash64("text"))
    return d.withColumn("_nth", F.row_number().over(w)).where("_nth = 1 or doc_id is null").select(*docs.columns)
