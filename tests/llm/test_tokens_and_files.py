import random
import zlib

import numpy as np
import pytest
from tokenizers import Tokenizer

from freqsketch.llm import packing, repair, separators
from freqsketch.llm.common import new_shared_dir
from freqsketch.llm.shared_files import atomic_writer, open_store, read_range, sizes
from freqsketch.llm.tokens import encoder, tokenizer_path

from .conftest import TEXTS, by_id


@pytest.fixture(scope="module")
def library():
    t = Tokenizer.from_file(tokenizer_path())
    return lambda x: t.encode(x or "", add_special_tokens=False).ids


def test_ids_equal_the_library(library):
    rnd = random.Random(1)
    texts = [t or "" for t in TEXTS] + ["".join(rnd.choice(" '\nsrevltmd1.é\t  　x日") for _ in range(rnd.randint(0, 30))) for _ in range(2000)]
    texts += ["<|endoftext|> x", "\x85a\x1cb", " \U0001fae0\U0001f6d8 new signs"]
    for part in (texts, texts[::-1], [""], []):
        ids, counts = encoder(tokenizer_path()).encode(part)
        assert counts.tolist() == [len(library(t)) for t in part]
        assert ids.tolist() == [i for t in part for i in library(t)]
    assert 50256 in library("<|endoftext|> x") and 50256 not in encoder(tokenizer_path(), escape=True).encode(["<|endoftext|> x"])[0]


def test_cache_survives_its_limit(library, monkeypatch):
    import freqsketch.llm.tokens as T

    monkeypatch.setattr(T, "STORE_IDS", 50)
    monkeypatch.setattr(T, "SLOT_BITS", 4)
    enc = T.WordEncoder(tokenizer_path())
    for t in TEXTS * 2:
        assert enc.encode([t or ""])[0].tolist() == library(t)


@pytest.mark.parametrize("seed", range(4))
def test_grammar_round_trip(seed):
    rnd = np.random.default_rng(seed)
    lengths = rnd.integers(0, 60, 40)
    ids = np.minimum(rnd.zipf(1.4, int(lengths.sum())), 300).astype(np.uint32)
    ids[:50] = 7  # chains of equal pairs
    keys = [None, -5, *range(38)]
    block = repair.Block(repair.pack_block(keys, lengths, ids, 50257))
    assert (block.ids() == ids).all() and (block.lengths == lengths).all() and block.keys == keys
    at = np.cumsum(lengths) - lengths
    for i in (0, 7, 39):
        assert block.document(i).tolist() == ids[at[i] : at[i] + lengths[i]].tolist()
        assert block.document(i, 3, 9).tolist() == ids[at[i] : at[i] + lengths[i]][3:9].tolist()

    def under(s):
        return [s] if s < 50257 else under(int(block.rules[s - 50257, 0])) + under(int(block.rules[s - 50257, 1]))

    assert [len(under(50257 + k)) for k in range(len(block.rules))] == block.expanded.tolist()
    assert block.n_symbols.sum() < len(ids) and len(block.rules)


def test_grammar_goes_on_until_no_pair_repays():
    rnd = np.random.default_rng(9)
    phrases = [rnd.integers(0, 50257, rnd.integers(40, 90)) for _ in range(5)]
    ids = np.concatenate([phrases[rnd.integers(5)] for _ in range(400)]).astype(np.uint32)
    g = repair.compress(ids, np.array([len(ids)]), 50257)
    s = g["symbols"].astype(np.uint64)
    pairs, counts = np.unique((s[:-1] << np.uint64(32)) | s[1:], return_counts=True)
    assert counts.max() < repair.LEAST_COUNT
    assert g["expanded"].max() > 64 and len(s) < len(ids) / 25
    assert repair.expand(g["symbols"], g["rules"], g["expanded"], 50257).tolist() == ids.tolist()


def test_an_empty_block():
    assert repair.Block(repair.pack_block([], np.zeros(0, np.int64), np.zeros(0, np.uint32), 50257)).ids().tolist() == []


def test_grammar_files(spark, docs, nothing, library):
    folder = new_shared_dir(spark, "g")
    store, where = open_store(folder)
    store.create_dir(where, recursive=True)
    index = repair.write_grammar_files(docs, "text", "doc_id", folder, tokenizer_path()).persist()
    got = by_id(repair.read_grammar_files(index, folder))
    start = 0
    for i, t in enumerate(TEXTS):
        a = np.array([*library(t), 0], "<u4")
        r = got[i * 3]
        assert (r.start, r.n_tokens, r.ids_crc32) == (start, len(a), zlib.crc32(a.tobytes()))
        start += len(a)
    # one document, read alone by the index
    at = index.orderBy("file", "block").first()
    block = repair.Block(read_range(f"{folder}/{at.file}", at["at"], at.bytes))
    for i, key in enumerate(block.keys):
        want = [*library(TEXTS[key // 3]), 0]
        assert repair.read_document(folder, at.file, at["at"], at.bytes, i, 2, 40).tolist() == want[2:40]
    empty = new_shared_dir(spark, "g")
    index = repair.write_grammar_files(nothing, "text", "doc_id", empty, tokenizer_path()).persist()
    assert repair.read_grammar_files(index, empty).count() == 0


@pytest.mark.parametrize("block", [2, 6, 64, 1 << 20])
def test_separators_across_blocks(spark, docs, library, block):
    folder = new_shared_dir(spark, "f")
    store, where = open_store(folder)
    store.create_dir(where, recursive=True)
    small = docs.where("length(text) < 400 or text is null")
    index = separators.write_flat_files(small, "text", "doc_id", folder, tokenizer_path()).persist()
    index.count()
    counts = separators.scan_separators(spark, folder, block_bytes=block)
    got = by_id(index.join(counts, ["file", "ordinal"]), "key")
    want = {i * 3: len(library(t)) for i, t in enumerate(TEXTS) if len(t or "") < 400}
    assert {k: r.n_tokens for k, r in got.items()} == want
    for name, size in sizes(folder):
        rows = counts.where(f"file = '{name}'").orderBy("ordinal").collect()
        assert [r.ordinal for r in rows] == list(range(len(rows)))
        assert sum(r.n_tokens + 1 for r in rows) * 2 == size


def test_file_without_last_separator(spark):
    folder = new_shared_dir(spark, "f")
    for name, ids in (("a.bin", [5, 6, 50256, 7]), ("b.bin", []), ("c.bin", [50256, 50256])):
        with atomic_writer(f"{folder}/{name}") as out:
            out.write(np.array(ids, "<u2").tobytes())
    got = sorted((r.file, r.start, r.n_tokens) for r in separators.scan_separators(spark, folder, block_bytes=4).collect())
    assert got == [("a.bin", 0, 2), ("a.bin", 3, 1), ("c.bin", 0, 0), ("c.bin", 1, 0)]
    assert read_range(f"{folder}/a.bin", 2, 4) == np.array([6, 50256], "<u2").tobytes()


def check_packing(rows, want, window):
    pieces, sequences = {}, {}
    for r in rows:
        pieces.setdefault(r.doc_id, []).append(r)
        sequences.setdefault(r.sequence_id, []).append(r)
    for doc, ids in want.items():
        at = 0
        for r in sorted(pieces[doc], key=lambda r: r.start):
            part = np.array(ids[at : at + r.length], "<u4")
            assert (r.start, r.ids_crc32, r.doc_tokens) == (at, zlib.crc32(part.tobytes()), len(ids))
            assert r.ids == part.tobytes() if "ids" in r else True
            at += r.length
        assert at == len(ids)
    short = 0
    for rs in sequences.values():
        at = 0
        for r in sorted(rs, key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at <= window
        short += at < window
    return short


def test_packing(spark, docs, nothing, library):
    rows = packing.pack_documents(docs, "text", "doc_id", tokenizer_path(), window=256).collect()
    want = {i * 3: [*library(t), 1] for i, t in enumerate(TEXTS)}
    assert check_packing(rows, want, 256) <= 1
    assert packing.pack_documents(nothing, "text", "doc_id", tokenizer_path()).count() == 0


def test_neighbours_follow_their_seed(spark):
    topics = [" ".join(f"{w}{i % 40}" for i in range(60)) for w in ("apple", "brick", "cloud")]
    rows = [(n, f"{topics[n % 3]} extra{n}") for n in range(30)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = packing.pack_documents(df, "text", "doc_id", tokenizer_path(), window=1024).orderBy("sequence_id", "offset").collect()
    order = [r.doc_id for r in got if r.start == 0]
    same = sum(a % 3 == b % 3 for a, b in zip(order, order[1:]))
    assert same >= 25


def test_scores_are_bm25():
    ids = np.array([10, 11, 12, 10, 10, 13, 12], np.uint16)
    lengths = np.array([3, 3, 1])
    marks = np.ones(1 << 16, bool)
    counts = np.zeros(1 << packing.TERM_BITS, np.int64)
    row, term, times = packing.document_terms(ids, lengths, marks)
    np.add.at(counts, term, 1)
    idf = np.log1p((3 - counts + 0.5) / (counts + 0.5))
    index = packing.ShardIndex(ids, lengths, marks, idf, 7 / 3)
    docs = [[10, 11, 12], [10, 10, 13], [12]]
    df = {t: sum(t in d for d in docs) for t in (10, 11, 12, 13)}

    def bm25(q, d):
        return sum(np.log1p((3 - df[t] + 0.5) / (df[t] + 0.5)) * d.count(t) * 2.2 / (d.count(t) + 1.2 * (0.25 + 0.75 * len(d) / (7 / 3))) for t in set(q))

    for i, q in enumerate(docs):
        assert index.scores(i) == pytest.approx([bm25(q, d) for d in docs], rel=1e-6)


def test_related_documents_meet_in_one_shard(spark):
    # related pairs lie in different parts of a table that fills many shards
    filler = [(n, " ".join(f"f{(n * 7 + j) % 5003}" for j in range(12))) for n in range(2000)]
    pairs = [(10000 + n, " ".join(f"pair{n}w{j}" for j in range(30))) for n in range(40)]
    rows = pairs + filler + [(n + 10000, f"{text} end{n}") for n, text in pairs]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartitionByRange(4, "doc_id")
    got = packing.pack_documents(df, "text", "doc_id", tokenizer_path(), window=512, shard_docs=64).collect()
    of, shards = {}, {}
    for r in got:
        of.setdefault(r.doc_id, set()).add(r.sequence_id)
        shards.setdefault(r.sequence_id >> 32, set()).add(r.doc_id)
    assert len(of) == 2080 and len(shards) >= 30 and max(map(len, shards.values())) <= 2 * 64
    assert sum(bool(of[10000 + n] & of[20000 + n]) for n in range(40)) >= 36


def test_tree_orders_like_points():
    rnd = np.random.default_rng(0)
    points = np.concatenate([rnd.normal(c, 0.05, (200, packing.PLACE_DIMS)) for c in range(4)])
    nodes = packing.fit_tree(points, 16)
    leaf = packing.leaf_of(points, nodes)
    assert leaf.max() < 16 and np.bincount(leaf, minlength=16).max() <= 60
    assert all(len(set(np.flatnonzero(leaf == k) // 200)) == 1 for k in range(16))
