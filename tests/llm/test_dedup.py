import hashlib
import random
import re

import numpy as np
import pytest

from freqsketch.llm import embeddings, minhash, suffixes
from freqsketch.llm.components import connected_components

from .conftest import BASE, TEXTS, by_id

LOWER = {i: i + 32 for i in range(65, 91)}


def shingles(text, n):
    w = re.findall(r"[^\x20\x09-\x0D]+", (text or "").translate(LOWER))
    return {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if len(w) >= n else ({tuple(w)} if w else set())


def classes(nodes, linked):
    """Smallest member of each node's class."""
    parent = {n: n for n in nodes}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in linked:
        a, b = find(a), find(b)
        parent[max(a, b)] = min(a, b)
    return {n: find(n) for n in nodes}


def brute_classes(texts, n):
    s = {k: shingles(t, n) for k, t in texts.items()}
    keys = sorted(s)
    links = [(a, b) for i, a in enumerate(keys) for b in keys[:i] if s[a] and 100 * len(s[a] & s[b]) >= 80 * len(s[a] | s[b])]
    return classes(keys, links), {k: len(v) for k, v in s.items()}


def mutated(rnd, words, changes):
    w = list(words)
    for _ in range(changes):
        w[rnd.randrange(len(w))] = f"new{rnd.random()}"
    return " ".join(w)


@pytest.mark.parametrize("words", [4, 5])
def test_near_duplicates(spark, docs, words):
    got = by_id(minhash.near_duplicate_classes(docs, "text", "doc_id", words), "id")
    want, sizes = brute_classes({i * 3: t for i, t in enumerate(TEXTS)}, words)
    assert {k: r.component_id for k, r in got.items()} == want
    assert {k: r.n_shingles for k, r in got.items()} == sizes


def test_large_family_in_blocks(spark, monkeypatch):
    """Near copies of all degrees, chains included, dealt over many blocks."""
    monkeypatch.setattr(minhash, "BLOCK_SHINGLES", 2000)
    rnd = random.Random(4)
    base = [f"b{i}" for i in range(150)]
    texts = {n: mutated(rnd, base, rnd.choice([1, 2, 3, 5, 6, 8])) for n in range(120)} | {n: mutated(rnd, [f"o{n}_{i}" for i in range(60)], 0) for n in range(120, 140)}
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    got = by_id(minhash.near_duplicate_classes(df, "text", "doc_id"), "id")
    want, _ = brute_classes(texts, 4)
    assert {k: r.component_id for k, r in got.items()} == want


def test_near_duplicates_of_nothing(spark, nothing):
    assert minhash.near_duplicate_classes(nothing, "text", "doc_id").count() == 0
    one = spark.createDataFrame([(5, None), (None, "some text of five words")], "doc_id long, text string")
    assert minhash.near_duplicate_classes(one, "text", "doc_id").count() == 2


def test_components(spark):
    rnd = random.Random(2)
    edges = [(rnd.randrange(300), rnd.randrange(300)) for _ in range(220)] + [(k, k + 1) for k in range(1000, 1060)] + [(5, 5), (None, 3)]
    got = {r.node: r.component for r in connected_components(spark.createDataFrame(edges, "a long, b long")).collect()}
    plain = [(a, b) for a, b in edges if a is not None and a != b]
    want = classes({x for e in plain for x in e}, plain)
    assert got == want
    assert connected_components(spark.createDataFrame([], "a long, b long")).count() == 0


def brute_removed(texts, length):
    seen = {}
    for b in texts.values():
        for p in range(len(b) - length + 1):
            seen[b[p : p + length]] = seen.get(b[p : p + length], 0) + 1
    out = {}
    for k, b in texts.items():
        gone = np.zeros(len(b), bool)
        for p in range(len(b) - length + 1):
            if seen[b[p : p + length]] > 1:
                gone[p : p + length] = True
        spans = int((np.diff(np.concatenate([[0], gone.astype(int)])) == 1).sum())
        out[k] = (len(b), int(gone.sum()), spans, hashlib.sha256(bytes(np.frombuffer(b, np.uint8)[~gone])).hexdigest())
    return out


def removal(df):
    return {r.id: (r.n_bytes, sum(s.hi - s.lo for s in r.spans), len(r.spans), r.kept_sha256) for r in suffixes.remove_repeats(df, "text", "doc_id").collect()}


@pytest.mark.parametrize("hot", [4096, 2])
def test_repeats(spark, monkeypatch, hot):
    monkeypatch.setattr(suffixes, "HOT", hot)
    monkeypatch.setattr(suffixes, "SHARD_BYTES", 3000)
    rnd = random.Random(8)
    passage = "".join(rnd.choice("abcdefgh é") for _ in range(260))
    noise = lambda n: "".join(rnd.choice("ijklmnop\n") for _ in range(n))
    texts = {n: noise(rnd.randrange(300)) + passage[rnd.randrange(60) : 260 - rnd.randrange(60)] + noise(rnd.randrange(300)) for n in range(40)}
    texts |= {50: noise(900), 51: None, 52: "", 53: passage[:199], 54: "z" * 700, 55: (noise(150) + passage) * 2, 56: BASE, 57: BASE}
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string").repartition(4)
    assert removal(df) == brute_removed({k: (t or "").encode() for k, t in texts.items()}, 200)
    assert suffixes.remove_repeats(df.where("doc_id < 0"), "text", "doc_id").count() == 0


def test_merged_lists_find_what_all_pairs_hold():
    """Collisions counted over posting lists with skips, against signatures compared one by one."""
    rnd = random.Random(5)
    base = [f"b{i}" for i in range(80)]
    texts = [mutated(rnd, base, rnd.choice([0, 1, 2, 4, 9, 30])).encode() for _ in range(70)]
    off = np.concatenate([[0], np.cumsum([len(t) for t in texts])])
    sets, n = minhash.shingle_sets(np.frombuffer(b"".join(texts), np.uint8), off, 4)
    sig = minhash.signatures(sets, n)
    ids, cls, begin = np.arange(70), np.arange(70), np.cumsum(n) - n
    side = lambda lo, hi: (ids[lo:hi], cls[lo:hi], sig[lo:hi], sets[begin[lo] : begin[hi - 1] + n[hi - 1]], n[lo:hi])
    a, b = minhash._links_between(side(0, 40), side(40, 70), minhash.MATCHES, 80)
    common = lambda x, y: len(np.intersect1d(sets[begin[x] : begin[x] + n[x]], sets[begin[y] : begin[y] + n[y]]))
    links = [(x, y) for x in range(40) for y in range(40, 70) if (sig[x] == sig[y]).sum() >= minhash.MATCHES and 100 * common(x, y) >= 80 * (n[x] + n[y] - common(x, y))]
    assert classes(range(70), zip(a.tolist(), b.tolist())) == classes(range(70), links) and len(links) > len(a)


def test_suffix_array_kernels():
    rnd = random.Random(3)
    segs = [bytes(rnd.choice(b"ab\x00") for _ in range(rnd.randint(1, 60))) for _ in range(40)]
    sizes = np.array([len(x) for x in segs])
    begins = np.cumsum(sizes) - sizes
    text, ends = np.frombuffer(b"".join(segs), np.uint8), np.repeat(begins + sizes, sizes)
    sa, words = suffixes.suffix_array(text, ends)
    suffix = lambda p: (text[p : ends[p]].tobytes(), int(p))
    assert [suffix(p) for p in sa] == sorted(suffix(p) for p in range(len(text)))

    def common(a, b):
        return next((i for i, (x, y) in enumerate(zip(a, b)) if x != y), min(len(a), len(b)))

    lcp = suffixes.common_prefixes(sa, words, begins, sizes)
    assert lcp.tolist() == [0] + [common(suffix(a)[0], suffix(b)[0]) for a, b in zip(sa, sa[1:])]


def brute_vectors(rows):
    """Links and smallest linked key of (key, vector) rows with unique keys."""
    good = {k: np.array(v, float) / np.max(np.abs(v)) for k, v in rows if v is not None and v and all(x is not None and np.isfinite(x) for x in v) and any(v)}
    keys = sorted(good)
    link = [(a, b) for i, a in enumerate(keys) for b in keys[:i] if len(good[a]) == len(good[b]) and good[a] @ good[b] / np.linalg.norm(good[a]) / np.linalg.norm(good[b]) >= 0.95]
    n = {k: 0 for k, _ in rows}
    for a, b in link:
        n[a] += 1
        n[b] += 1
    return n, classes(n, link)


@pytest.mark.parametrize("block,leaf,fan", [(4096, 128, 256), (12, 4, 3)])
def test_vectors(spark, monkeypatch, block, leaf, fan):
    monkeypatch.setattr(embeddings, "LEAF", leaf)
    monkeypatch.setattr(embeddings, "FAN", fan)
    rnd = np.random.default_rng(1)
    centres = rnd.normal(size=(12, 16))
    rows = [(n, (centres[n % 12] + rnd.normal(size=16) * rnd.choice([0.05, 0.3])).astype(np.float32).tolist()) for n in range(150)]
    rows += [(200 + k, rows[0][1]) for k in range(5)] + [(300, None), (301, []), (302, [0.0] * 16), (303, [float("nan")] * 16), (304, [1.0, None]), (305, rows[0][1][:8]), (306, rows[0][1][:8]), (307, [float("inf")] * 16)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>").repartition(3)
    got = by_id(embeddings.vector_links(df, "vec_id", "embedding", block=block), "id")
    n, c = brute_vectors(rows)
    assert {k: r.n_links for k, r in got.items()} == n
    assert {k: r.component_id for k, r in got.items()} == c
    assert embeddings.vector_links(df.where("vec_id < 0"), "vec_id", "embedding").count() == 0


def test_vectors_are_shuffled_once_however_many_pairs(spark):
    """40 blocks make 820 pairs; what is shuffled stays a few times the vectors."""
    from freqsketch.operators.costs import _stages

    v = np.random.default_rng(7).normal(size=(480, 64)).astype(np.float32)
    df = spark.createDataFrame([(n, x.tolist()) for n, x in enumerate(v)], "vec_id long, embedding array<float>").repartition(2).localCheckpoint()
    before = set(_stages(spark))
    assert embeddings.vector_links(df, "vec_id", "embedding", block=12).count() == 480
    assert sum(int(s.shuffleWriteBytes()) for k, s in _stages(spark).items() if k not in before) < 6 * v.nbytes
