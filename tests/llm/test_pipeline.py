"""Every stage of the pipeline against a brute-force version over the input that it had."""

import base64
import hashlib
import re
import struct

import public_tokenizers as P
import tiktoken

import corpus_pipeline

SF = "/root/testdata/sf0.001"
SPACE = re.compile(rb"[^\x20\x09-\x0D]+")
ALNUM = re.compile(rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
LOW = bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz")
DIGEST = ("doc_id", "n_tokens", "ids_sha256", "decoded_sha256")


def words(pattern, text):
    return pattern.findall((text or "").encode().translate(LOW))


def norm(line):
    return re.sub(r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+", " ", line.lower()).strip()


def smallest_of_groups(texts):
    sets = {}
    for k, t in texts.items():
        w = words(SPACE, t)
        sets[k] = {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())
    root = {k: k for k in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in sorted(sets):
        for b in sorted(sets):
            if a < b and sets[a] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {find(k) for k in sets}


def contaminated(texts, items):
    keys = set()
    for t in items:
        w = words(ALNUM, t)
        keys |= {tuple(w[i : i + 13]) for i in range(max(1, len(w) - 12) if w else 0)}
    lengths, out = {len(k) for k in keys}, set()
    for doc, t in texts.items():
        w = words(ALNUM, t)
        hit = [0] * len(w)
        for n in lengths:
            for i in range(len(w) - n + 1):
                if tuple(w[i : i + n]) in keys:
                    hit[i : i + n] = [1] * n
        if sum(hit) > 0 and 20 * sum(hit) >= len(w):
            out.add(doc)
    return out


def test_stages(spark, monkeypatch):
    held, put = {}, corpus_pipeline.written

    def keep(df, name):
        held[name.removeprefix("pipeline-")] = out = put(df, name)
        return out

    monkeypatch.setattr(corpus_pipeline, "written", keep)
    last = {tuple(r[c] for c in DIGEST) for r in corpus_pipeline.run(spark, SF).collect()}
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    assert all(df.columns == docs.columns for df in held.values()) and list(held) == [n for n, _ in corpus_pipeline.STAGES[:-1]]
    texts = {n: {r["doc_id"]: r["text"] for r in df.collect()} for n, df in {"documents": docs, **held}.items()}

    # toxicity: rows are kept as they are, ordinary documents stay, and no larger share of the toxic ones
    tox = texts["toxicity"]
    assert tox.items() <= texts["documents"].items()
    labels = spark.read.parquet(f"{SF}/labels.parquet").where("toxic is not null").collect()
    share = lambda v: (lambda ids: sum(i in tox for i in ids) / max(1, len(ids)))([r["doc_id"] for r in labels if r["toxic"] == v])
    assert share(0) > 0.9 and share(0) >= share(1)

    # lines: only lines go, first occurrences of equal lines stay, what stays is in order
    seen, lines = set(), texts["line_dedup"]
    for doc in sorted(tox):
        before, after = (tox[doc] or "").split("\n"), (lines.get(doc) or "").split("\n")
        rest = iter(before)
        assert doc not in lines or lines[doc] == tox[doc] or all(x in rest for x in after)
        with_words = [norm(x) for x in after if norm(x)]
        assert not seen & set(with_words) and len(set(with_words)) == len(with_words)
        seen |= set(with_words)
        assert doc in lines or any(norm(x) for x in before)

    groups = texts["ngram_jaccard_join"]
    assert groups == {k: lines[k] for k in smallest_of_groups(lines)}

    items = [r["text"] for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    clean = texts["benchmark_decontamination"]
    assert clean == {k: t for k, t in groups.items() if k not in contaminated(groups, items)}

    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(P.path("byte_bpe_multi_50k.tiktoken"), "rb"))}
    enc = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    want = set()
    for k, t in clean.items():
        ids = enc.encode_ordinary(t or "")
        want.add((k, len(ids), hashlib.sha256(struct.pack(f"<{len(ids)}I", *ids)).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest()))
    assert last == want
