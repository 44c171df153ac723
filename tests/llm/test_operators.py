"""Brute-force versions over a small table with the awkward cases in it."""

import collections
import hashlib
import random
import re

import numpy as np
import public_tokenizers as P
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from anglegraph.llm import byte_bpe, components, decontaminate, jaccard_join, licenses, line_dedup, quality, substring_dedup, suffix_dedup, token_counts, toxicity

SPACE = re.compile(rb"[^\x20\x09-\x0D]+")
ALNUM = re.compile(rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
LOW = bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz")
PASSAGE = " ".join(f"shared{i}" for i in range(60))


def texts():
    r = random.Random(3)
    word = lambda: "".join(r.choice("abcdeé") for _ in range(r.randint(1, 7)))
    some = lambda n: " ".join(word() for _ in range(n))
    base = some(120)
    near = base.split(" ")
    near[5] = "changed"
    return [
        None, "", " \n\t ", "one", "a b c d", base, base, " ".join(near), base + ".", some(90) + " " + PASSAGE + " " + some(40), PASSAGE, some(30) + "\n" + PASSAGE + "\n" + some(10),
        "x" * 700, "ab" * 400, "no spaces" * 60, some(5000), "Licensed under the Apache License, Version 2.0\nMIT license mit license", "<|endoftext|> and  two  spaces\r\n\r\n't 's", "Kelvin İ GNU General Public License v3",
        "line one is here now ok.\nline one is here now ok.\nLine One is here now, ok!\nshort", "日本語 テキスト " * 50, "😀" * 300 + " é́",
    ]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i if i != 3 else None, t, "x", "y") for i, t in enumerate(texts())]
    return spark.createDataFrame(rows, "doc_id long, text string, block string, part string").repartition(3).cache()


def raw():
    return {(i if i != 3 else None): (t or "").encode() for i, t in enumerate(texts())}


def rows(df):
    return {r["doc_id"]: tuple(r)[1:] for r in df.collect()}


def sha(b):
    return hashlib.sha256(b).hexdigest()


def test_op1(docs):
    all_, n = raw(), collections.Counter()
    for t in all_.values():
        n.update(t[i : i + 200] for i in range(len(t) - 199))
    want = {}
    for k, t in all_.items():
        gone = bytearray(len(t))
        for i in range(len(t) - 199):
            if n[t[i : i + 200]] > 1:
                gone[i : i + 200] = b"\1" * 200
        want[k] = (len(t), sum(gone), len(re.findall(b"\1+", gone)), sha(bytes(b for b, g in zip(t, gone) if not g)))
    assert rows(suffix_dedup.remove_repeated_bytes(docs)) == want


def test_block_order():
    r = random.Random(1)
    for _ in range(100):
        x = bytes(r.choice(b"ab") for _ in range(r.randint(0, 60))) * r.randint(1, 3)
        assert suffix_dedup.block_suffix_order(x).tolist() == sorted(range(len(x)), key=lambda i: x[i:])


def test_op2(docs):
    words = {k: SPACE.findall(t) for k, t in raw().items()}
    n = collections.Counter(tuple(w[i : i + 35]) for w in words.values() for i in range(len(w) - 34))
    want = {}
    for k, w in words.items():
        gone = [False] * len(w)
        for i in range(len(w) - 34):
            if n[tuple(w[i : i + 35])] > 1:
                gone[i : i + 35] = [True] * 35
        want[k] = (len(w), sum(gone), sha(b" ".join(x for x, g in zip(w, gone) if not g)))
    assert rows(substring_dedup.remove_repeated_windows(docs)) == want


def test_op3(docs):
    path = P.path("byte_bpe_multi_50k.tiktoken")
    enc = byte_bpe.encoder(open(path, "rb").read(), P.PATTERN)
    want = {}
    for k, t in raw().items():
        ids = enc.encode_ordinary(t.decode())
        want[k] = (len(ids), sha(np.array(ids, "<u4").tobytes()), sha(t))
    assert rows(byte_bpe.round_trip(docs, path, P.PATTERN)) == want
    back = byte_bpe.decode(byte_bpe.encode(docs.select("doc_id", "text"), path, P.PATTERN), path, P.PATTERN)
    assert all(bytes(r["decoded"]) == (r["text"] or "").encode() for r in back.collect())


def test_op3_long_pieces():
    enc = byte_bpe.encoder(open(P.path("byte_bpe_multi_50k.tiktoken"), "rb").read(), P.PATTERN)
    text = " ".join(f"word{i}  \n\n x'll" for i in range(20000))
    assert len(list(byte_bpe.safe_pieces(text))) > 2
    assert byte_bpe.encode_text(enc, text).tolist() == enc.encode_ordinary(text)


def test_op4(docs):
    got = rows(licenses.scan_licenses(docs))
    for k, t in raw().items():
        w = [x.decode() for x in ALNUM.findall(t.translate(LOW))]
        at, names = [], set()
        for phrase, label in licenses.BASE:
            q = phrase.split()
            for i in range(len(w) - len(q) + 1):
                if w[i : i + len(q)] == q:
                    at.append(i)
                    names.add(label)
        assert got[k][:5] == (len(w), len(at), min(at, default=None), max(at, default=None), ",".join(sorted(names)))
        assert names <= set(got[k][5].split(",")) and 0 <= got[k][6] <= 1


def plain_scan(text):
    """The labels and score of one text by Python's own regular expressions."""
    t = " " + " ".join(x.decode() for x in ALNUM.findall(text.encode().translate(LOW))) + " "
    base = {label for phrase, label in licenses.BASE if f" {phrase} " in t}
    spans = [(m.start(), m.end(), p, label) for p, label, key, x in licenses.rules() if f" {key} " in t for m in re.finditer(f"(?<= )({x})(?= )", t)]
    left = [a for a in spans if not any(b[0] <= a[0] and b[1] >= a[1] and (b[2] > a[2] or b[2] == a[2] and b[1] - b[0] > a[1] - a[0]) for b in spans)]
    score = max([a[2] / licenses.SCORED for a in left] + [0.5 if base else 0.0])
    return ",".join(sorted(base | {a[3] for a in left})), score


def test_op4_labels(spark):
    r = random.Random(5)
    told = ["see agpl 3 then gpl 3 now", "lgpl 3 or gpl 3", "agpl 3 license or gpl 3 license", "isc license", "mozilla public license", "bsd style license", "the unlicense", "gnu gpl", "apache tribes", "SPDX-License-Identifier: GPL-2.0-only, gpl 2", "gpl 3 or any later version; gpl 3", "CC BY-SA 4.0 and cc by"]
    bits = ["gpl", "agpl", "lgpl 2", "gpl 3", "v 3", "version 2 0", "or later", "licensed under the", "gnu general public license", "gnu lesser general public license", "apache license", "apache 2 0", "mit license", "bsd 3", "cc by sa 4 0", "all rights reserved", "x", "the", "spdx license identifier"]
    told += [" ".join(r.choice(bits) for _ in range(r.randint(1, 14))) for _ in range(150)]
    d = spark.createDataFrame(list(enumerate(told)), "doc_id long, text string").repartition(4)
    got = rows(licenses.scan_licenses(d))
    assert {k: got[k][5:] for k in got} == {i: plain_scan(t) for i, t in enumerate(told)}
    assert [got[i][5] for i in range(9)] == ["agpl,gpl", "gpl,lgpl", "agpl,gpl", "isc", "mpl", "bsd", "unlicense", "gpl", ""]


def test_op5(docs):
    from tokenizers import Tokenizer

    tk = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    want = {k: (len(t), n := len(tk.encode(t.decode(), add_special_tokens=False).ids), n > 1024) for k, t in raw().items()}
    assert rows(token_counts.count_tokens(docs, P.path("byte_bpe_50k.json"))) == want


def test_op6(spark):
    r = random.Random(2)
    word = lambda: "".join(r.choice("abcdef") for _ in range(5))
    data = [(i, " ".join(word() if i % 3 or j % 6 else "vilestuff" for j in range(60)), int(i % 3 == 0)) for i in range(300)]
    d = spark.createDataFrame([(i, t) for i, t, _ in data] + [(900, None), (901, "")], "doc_id long, text string")
    labels = spark.createDataFrame([(i, y) for i, _, y in data], "doc_id long, toxic int")
    got = rows(toxicity.score_toxicity(d, labels))
    held = [(got[i][2], y) for i, _, y in data if got[i][0]]
    assert held and np.mean([p == y for p, y in held]) > 0.95
    assert len(got) == 302 and all(0 <= v[1] <= 1 for v in got.values())
    assert {r["doc_id"] for r in toxicity.reject_toxic(d, labels).collect()} >= {900, 901}
    assert toxicity.score_toxicity(d, labels.where("toxic = 0")).where("predicted = 1").count() == 0


def test_word_model_equals_plain_kneser_ney(spark):
    r = random.Random(8)
    some = ["ab", "cd", "ef", "gh", "ij", "kl", "mn"]
    data = [(i, " ".join(r.choice(some[: 4 + 3 * (i % 2)]) for _ in range(r.randint(1, 12))), i % 2) for i in range(40)]
    rest = [(100 + i, " ".join(r.choice([*some, "new", "other"]) for _ in range(8))) for i in range(60)]
    docs = spark.createDataFrame([(i, t) for i, t, _ in data] + rest, "doc_id long, text string").repartition(3)
    sample = spark.createDataFrame([(y, False, t, 1.0) for _, t, y in data], "toxic int, curve boolean, text string, weight double").repartition(2)
    model = toxicity._fit_words(docs, sample)

    shared = collections.Counter(w for _, t in [(i, t) for i, t, _ in data] + rest for w in t.split())
    pairs = [collections.Counter((a, b) for _, t, y in data if y == c for a, b in zip(["", *t.split()], t.split())) for c in (0, 1)]

    def discount(counts):
        n = collections.Counter(counts)
        return n[1] / (n[1] + 2 * n[2]) if n[1] else 0.5

    known_words = {w for w in shared if sum(len({x for x in q if x[1] == w}) for q in pairs) > 1}

    def p(c, a, b):
        after = {w: sum(1 for x in pairs[c] if x[1] == w) for w in shared}
        d, whole = discount(after.values()), sum(after.values())
        backoff = max(1e-9, d * sum(v > 0 for v in after.values()) / whole)
        low = max(after.get(b, 0) - d, 0) / whole + backoff * (shared[b] + 0.5) / (sum(shared.values()) + 0.5 * len(shared)) if b in known_words else backoff
        if a not in known_words:
            return low  # the first word of a text stands without a context
        d, seen = discount(pairs[c].values()), sum(n for (x, _), n in pairs[c].items() if x == a)
        part = {x: max(n - d, 0) / max(1, seen) for x, n in pairs[c].items() if x[0] == a and sum(q[x] for q in pairs) > 1}
        return part.get((a, b), 0) + max(1e-9, 1 - sum(part.values())) * low

    told = ["ab cd ef", "new ab", "kl mn kl mn other cd", "ij"]
    want = [sum(np.log(p(1, a, b)) - np.log(p(0, a, b)) for a, b in zip(["", *t.split()], t.split())) for t in told]
    import pyarrow as pa

    *_, place, rows_, n_rows, known = toxicity._words(pa.array(told), toxicity.K.Powers())
    assert np.allclose(model.ratios(place, rows_, known, n_rows), want)


def test_toxicity_keeps_clashing_columns(spark):
    data = [(i, "vile stuff here" if i % 3 == 0 else "a kind word here", "s", "r", "t") for i in range(120)]
    d = spark.createDataFrame(data, "doc_id long, text string, _score string, row string, score string")
    labels = spark.createDataFrame([(i, int(i % 3 == 0)) for i in range(120)], "doc_id long, toxic int")
    out = toxicity.reject_toxic(d, labels)
    assert out.columns == d.columns and {tuple(x)[2:] for x in out.collect()} == {("s", "r", "t")} and 0 < out.count() < 120


def test_toxicity_scores_large_batches_in_little_memory(spark):
    import tracemalloc

    from anglegraph.llm import toxicity

    r = random.Random(15)
    some = words(r, 3000)
    texts = [" ".join(r.choices(some, k=300)) for _ in range(8000)]
    batch = pa.RecordBatch.from_pydict({"text": texts})
    pw = toxicity.K.Powers()
    d = spark.createDataFrame([(i, texts[i]) for i in range(40)], "doc_id long, text string")
    model = toxicity.fit(d, d.selectExpr("doc_id", "cast(doc_id % 2 as int) as toxic"))
    tracemalloc.start()
    for a, b in toxicity.row_ranges(toxicity.K.text_buffer(batch.column(0))[1], toxicity.CHUNK):
        model.scores(batch.column(0).slice(a, b - a), pw)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 100 << 20


def test_curve_never_falls():
    x, y = np.array([-0.4, -0.3, 0.1, 0.2, 0.3]), np.array([1.0, 0.0, 0.0, 0.0, 0.0])
    a, b = toxicity._fit_curve(x, y)
    both = toxicity._fit_curve(np.stack([x, -x], axis=1), 1 - y)
    assert both[1] > 0 and both[2] == 0
    assert b == 0 and a < 0 and toxicity._fit_curve(x, 1 - y)[1] > 0 and toxicity._fit_curve(x, np.array([1.0, 1.0, 1.0, 0.0, 0.0])) == (-1e-9, 0.0)


def test_toxicity_keeps_the_base_rate_when_one_class_is_cut(spark):
    r = random.Random(21)
    texts = [" ".join(words(r, 30)) for _ in range(3000)]  # labels that say nothing: every score is near the share of toxic rows
    d = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i % 9 == 0)) for i in range(3000)], "doc_id long, toxic int")
    held = [s["score"] for s in toxicity.score_toxicity(d, labels, curve_rows=60).collect() if s["held_out"]]
    assert abs(np.mean(held) - 1 / 9) < 0.05


def test_op7(docs, spark):
    got = rows(line_dedup.line_decisions(docs))
    assert len(got) == len(texts()) and got[19][:2] == (4, 2)
    assert got[6][1] == 1 and got[8][1] == 1  # the copies of document 5 lose their only line
    kept = {r["doc_id"]: r["text"] for r in line_dedup.dedup_lines(docs).collect()}
    assert kept[19] == "line one is here now ok.\nshort" and 6 not in kept and kept[1] == "" and kept[5] == texts()[5]
    assert 7 not in kept or kept[7] == texts()[7]


def words(r, n):
    return ["".join(r.choice("abcdefghijklmnop") for _ in range(r.randint(2, 9))) for _ in range(n)]


def line_groups(spark, lines):
    """The connected groups of edit similarity 0.9, from all pairs."""
    d = spark.createDataFrame(list(enumerate(lines)), "i int, x string")
    close = d.alias("a").join(d.alias("b"), F.expr("a.i < b.i and 9 * greatest(length(a.x), length(b.x)) <= 10 * least(length(a.x), length(b.x))"))
    root = list(range(len(lines)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for a, b in close.where("10 * levenshtein(a.x, b.x) <= greatest(length(a.x), length(b.x))").select("a.i", "b.i").collect():
        a, b = find(a), find(b)
        root[max(a, b)] = min(a, b)
    return {i for i in range(len(lines)) if find(i) == i}


def kept_lines(spark, lines):
    d = spark.createDataFrame(list(enumerate(lines)), "doc_id long, text string").repartition(3)
    return {r["doc_id"] for r in line_dedup.line_decisions(d).collect() if not r["n_removed"]}


def test_op7_finds_the_similar_lines_of_all_pairs(spark):
    r = random.Random(11)
    lines = []
    for n in (2, 3, 5, 8, 12, 20, 20, 35, 50, 50, 90):  # words replaced: about 5 of 100 characters
        base = words(r, n)
        lines.append(" ".join(base))
        for _ in range(6):
            near = list(base)
            for _ in range(max(1, n // 20)):
                near[r.randrange(n)] = words(r, 1)[0]
            lines.append(" ".join(near))
    for n in [*range(9, 56)] * 2:  # short lines: any edits up to one in ten characters
        base = "".join(r.choice("abcd ") for _ in range(n)).split()
        near = list(" ".join(base))
        for _ in range(n // 10):
            at = r.randrange(1, len(near) - 1)
            near[at : at + r.randint(0, 1)] = r.choice(["", "z"])
        lines += [" ".join(base), " ".join("".join(near).split())]
    lines += ["漢字仮名交文字列" * 9 + "甲乙丙丁", "漢字仮名交文字列" * 9 + "甲乙戊丁", "x" * 700, "x" * 690]
    assert kept_lines(spark, lines) == line_groups(spark, lines)


def test_op7_loses_no_link_of_a_large_block(spark, monkeypatch):
    monkeypatch.setattr(line_dedup, "FEW", 4)
    r = random.Random(12)
    base, other = words(r, 60), words(r, 60)
    chain = [" ".join([*other[:i], *base[i:]]) for i in range(31)]  # each is similar to a few before and after it only
    star = [" ".join([*base[:40], *base[41 + i : 45 + i], *words(r, 6), *base[40:]]) for i in range(12)]
    assert kept_lines(spark, chain + star) == line_groups(spark, chain + star)


def test_op7_finds_links_that_share_no_words(spark, monkeypatch):
    monkeypatch.setattr(line_dedup, "PLACES", 1 << 10)
    r = random.Random(14)
    lines = []
    for n in (50, 57, 64, 72, 81, 89, 90, 99, 100, 143, 190, 505, 512, 700, 1300):  # one edit in ten characters, evenly spread
        base = [r.choice("abcdefghijklm") for _ in range(n)]
        for i in range(4, n - 1, 6):
            base[i] = " "
        changed, dropped, put = list(base), list(base), list(base)
        for i in range(n // 10):
            changed[10 * i + 3 + (10 * i + 3) % 6 // 4] = "z"
            put.insert(11 * i + 5, "y")
        for i in reversed(range(n // 10)):
            del dropped[10 * i + 2]
        lines += [" ".join("".join(x).split()) for x in (base, changed, dropped, put)]
    assert kept_lines(spark, lines) == line_groups(spark, lines)


def test_op7_compares_the_lines_of_all_turns_once_and_large_groups_with_others(spark, monkeypatch):
    monkeypatch.setattr(line_dedup, "PLACES", 1 << 14)
    monkeypatch.setattr(line_dedup, "MANY", 2, raising=False)
    r = random.Random(16)
    lines = []
    for n in (60, 130, 300, 620, 2600):
        base = [r.choice("abcdefghijklm") for _ in range(n)]
        for i in range(4, n - 1, 6):
            base[i] = " "
        other = list(base)  # one edit in ten characters, in every second word or more: the two groups share no sketch
        for i in range(n // 10 - 2):
            other[10 * i + 3 + (10 * i + 3) % 6 // 4] = "z"
        for x in (base, other):
            lines += [" ".join("".join(x[:-1] + [c]).split()) for c in "nopqr"]
        lines.append(" ".join("".join(r.choice("abcdefghijklm ") for _ in range(n)).split()))
    calls, similar = [], line_dedup._similar

    def counted(pairs, texts, sketched=True):
        calls.append(sketched)
        return similar(pairs, texts, sketched)

    monkeypatch.setattr(line_dedup, "_similar", counted)
    assert kept_lines(spark, lines) == line_groups(spark, lines)
    assert calls.count(False) == 1


def test_op7_compares_long_lines_within_the_bound(spark):
    r = random.Random(13)
    opened, passage = words(r, 1300), words(r, 1600)
    lines = [" ".join(opened), " ".join([*words(r, 12), *opened]), " ".join(passage), " ".join([*passage[:300], *words(r, 60), *passage[360:]])]
    assert kept_lines(spark, lines) == {0, 2} == line_groups(spark, lines)


def test_op8(docs):
    sets = {}
    for k, t in raw().items():
        w = SPACE.findall(t.translate(LOW))
        sets[k] = {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())
    root = {k: k for k in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = [k for k in sets if k is not None]
    for a in ids:
        for b in ids:
            if a < b and sets[a] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    want = {k: (len(s), find(k)) for k, s in sets.items()}
    assert rows(jaccard_join.join_documents(docs)) == want
    assert sorted(r["doc_id"] for r in jaccard_join.keep_one(docs).collect() if r["doc_id"] is not None) == sorted({v[1] for k, v in want.items() if k is not None})


def test_tree_walk_loses_no_link():
    r = np.random.default_rng(5)
    base = [np.unique(r.integers(1, 1 << 60, 80).astype(np.uint64)) for _ in range(30)]
    sets = [np.unique(np.concatenate([b[: len(b) - c], r.integers(1, 1 << 60, c).astype(np.uint64)])) for b in base for c in (0, 3, 8, 20)]
    root = list(range(len(sets)))

    def find(x, up):
        while up[x] != x:
            x = up[x]
        return x

    for i in range(len(sets)):
        for j in range(i):
            both = len(np.intersect1d(sets[i], sets[j]))
            if 100 * both >= 80 * (len(sets[i]) + len(sets[j]) - both):
                a, b = find(i, root), find(j, root)
                root[max(a, b)] = min(a, b)
    other = list(range(len(sets)))
    half = len(sets) // 2
    links = jaccard_join.link_sets(sets[:half], sets[half:]) + jaccard_join.link_sets(sets[:half]) + [(i + half, j + half) for i, j in jaccard_join.link_sets(sets[half:])]
    for i, j in links:
        a, b = find(i, other), find(j, other)
        other[max(a, b)] = min(a, b)
    assert [find(i, other) for i in range(len(sets))] == [find(i, root) for i in range(len(sets))]


def test_op9(docs, spark):
    bench = spark.createDataFrame([(1, PASSAGE), (2, "mit license"), (3, None), (4, " ".join(PASSAGE.split()[10:30]) + " other words"), (5, PASSAGE)], "item_id long, text string")
    win = collections.defaultdict(set)
    for r in bench.collect():
        w = ALNUM.findall((r["text"] or "").encode().translate(LOW))
        for i in range(max(1, len(w) - 12) if w else 0):
            win[tuple(w[i : i + 13])].add(str(r["item_id"]))
    want = {}
    for k, t in raw().items():
        w = ALNUM.findall(t.translate(LOW))
        hit, items = [0] * len(w), set()
        for key, ids in win.items():
            for i in range(len(w) - len(key) + 1):
                if tuple(w[i : i + len(key)]) == key:
                    hit[i : i + len(key)] = [1] * len(key)
                    items |= ids
        want[k] = (len(w), sum(hit), len(items), sha(",".join(sorted(items)).encode()), sum(hit) > 0 and 20 * sum(hit) >= len(w))
    assert rows(decontaminate.contamination(docs, bench)) == want
    kept = {r["doc_id"] for r in decontaminate.filter_contaminated(docs, bench).collect()}
    assert kept == {k for k, v in want.items() if not v[4]}
    cut = {r["doc_id"]: r["text"] for r in decontaminate.filter_contaminated(docs, bench, mode="cut").collect()}
    assert "shared20" not in cut[9] and cut[5] == texts()[5]


def test_op10(docs):
    got = rows(quality.judge_documents(docs))
    word = re.compile(r"[^\x20\x09-\x0D]+")
    for k, t in raw().items():
        t = t.decode()
        w = word.findall(t)
        n = collections.Counter(tuple(w[i : i + 3]) for i in range(len(w) - 2))
        again = [0] * len(w)
        for i in range(len(w) - 2):
            if n[tuple(w[i : i + 3])] > 1:
                again[i : i + 3] = [1] * 3
        lines = [x for x in t.split("\n") if word.search(x)]
        failed = len(w) < 50 or 100 * sum(again) > 50 * len(w)
        assert got[k][:6] == (len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), sum(again), failed), k
        assert not (failed and got[k][6])


def test_empty_tables(spark):
    none = spark.createDataFrame([], "doc_id long, text string")
    bench = spark.createDataFrame([], "item_id long, text string")
    labels = spark.createDataFrame([], "doc_id long, toxic int")
    for df in (suffix_dedup.remove_repeated_bytes(none), substring_dedup.remove_repeated_windows(none), licenses.scan_licenses(none), token_counts.count_tokens(none, P.path("byte_bpe_50k.json")), toxicity.score_toxicity(none, labels), line_dedup.line_decisions(none), jaccard_join.join_documents(none), decontaminate.contamination(none, bench), quality.judge_documents(none)):
        assert df.count() == 0


def test_components(spark):
    e = spark.createDataFrame([(1, 2), (2, 3), (9, 8), (5, 5), (3, 7), (7, 1)], "a long, b long")
    assert {tuple(r) for r in components.connected_components(e).collect()} == {(1, 1), (2, 1), (3, 1), (7, 1), (8, 8), (9, 8)}


def test_op7_leaves_no_texts_or_keys_in_scratch(spark):
    from anglegraph.llm import common
    from anglegraph.llm.line_dedup import line_decisions

    held = set(common._roots)
    words = [f"w{i}" for i in range(40)]
    lines = [" ".join(words[i % 7 :] + [str(i)]) for i in range(60)] + ["one short line here"] * 3
    out = line_decisions(spark.createDataFrame([(i, t) for i, t in enumerate(lines)], "doc_id long, text string"))
    assert sum(r["n_removed"] for r in out.collect()) > 2
    left = {p.rsplit("/", 1)[-1].rsplit("-", 1)[0] for p in set(common._roots) - held}
    assert "line-named" in left and not left & {"line-pieces", "line-keys", "line-open", "line-shared", "line-leaders"}
