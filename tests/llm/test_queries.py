"""Every registered query and every stage, over awkward tables, against brute force."""

import hashlib
import zlib
from collections import Counter

import corpus_pipeline
import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from freqsketch.llm import secrets
from freqsketch.llm.registry import ORACLES, QUERIES
from freqsketch.llm.tokens import tokenizer_path

from .conftest import ROWS, VECTORS, bag
from .test_dedup import brute_removed, classes, shingles
from .test_rows import WORD, brute_spans, brute_statistics, brute_targets, check_verdicts, reference_verdicts

NAMES = {int(n[2:].split("_")[0]): n for n in QUERIES if n.startswith("op")}


@pytest.fixture(scope="module")
def ids():
    t = Tokenizer.from_file(tokenizer_path())
    return lambda x: t.encode(x or "", add_special_tokens=False).ids


def answer(spark, folder, n):
    return QUERIES[NAMES[n]](spark, folder)


@pytest.mark.parametrize("n", range(1, 11))
def test_empty_tables(spark, awkward, empty, n):
    assert answer(spark, empty, n).count() == 0


def crc(values):
    return zlib.crc32(np.array(values, "<u4").tobytes())


def check_pieces(rows, want, window=2048):
    """Pieces of documents with keys that repeat: every id lies in one piece."""
    rows = [r.asDict() for r in rows]
    sequences = {}
    for r in rows:
        sequences.setdefault(r["sequence_id"], []).append(r)
    for rs in sequences.values():
        at = 0
        for r in sorted(rs, key=lambda r: r["offset"]):
            assert r["offset"] == at
            at += r["length"]
        assert at <= window
    left = Counter((r["doc_id"], r["start"], r["length"], r["ids_crc32"], r["doc_tokens"]) for r in rows)
    starts = {}
    for key, start, length, *_ in left:
        starts.setdefault(key, set()).add((start, length))
    for key, values in want:
        at = 0
        while at < len(values):
            part = next(n for s, n in starts[key] if s == at and left[key, s, n, crc(values[s : s + n]), len(values)])
            left[key, at, part, crc(values[at : at + part]), len(values)] -= 1
            at += part
    assert not +left


def test_packing(spark, awkward, ids):
    rows = answer(spark, awkward, 1).collect()
    check_pieces(rows, [(k, [*ids(t), 1]) for k, t in ROWS])


def brute_rows(rows, words):
    """(set sizes, smallest key of each row's class, rows by class); null keys stand alone."""
    sets = [shingles(t, words) for _, t in rows]
    can = [i for i, (k, _) in enumerate(rows) if k is not None and sets[i]]
    link = [(a, b) for a in can for b in can if b < a and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b])]
    root = classes(range(len(rows)), link)
    members = {}
    for i in range(len(rows)):
        members.setdefault(root[i], []).append(i)
    least = {r: min((rows[i][0] for i in m if rows[i][0] is not None), default=None) for r, m in members.items()}
    return [len(s) for s in sets], [least[root[i]] for i in range(len(rows))], list(members.values())


def test_near_duplicates(spark, awkward):
    sizes, least, _ = brute_rows(ROWS, 4)
    want = [(k, n, c, k == c) for (k, _), n, c in zip(ROWS, sizes, least)]
    assert bag(answer(spark, awkward, 2).select("doc_id", "n_shingles", "component_id", "kept").collect()) == bag(want)


def test_vectors(spark, awkward):
    good = []
    for i, (k, v) in enumerate(VECTORS):
        if k is not None and v and all(x is not None and np.isfinite(x) for x in v) and any(v):
            u = np.array(v) / np.max(np.abs(v))
            good.append((i, u / np.linalg.norm(u)))
    link = [(a, b) for a, x in good for b, y in good if b < a and x @ y >= 0.95]
    root = classes(range(len(VECTORS)), link)
    degree = Counter(x for e in link for x in e)
    least = {r: min((VECTORS[i][0] for i in range(len(VECTORS)) if root[i] == r and VECTORS[i][0] is not None), default=None) for r in set(root.values())}
    want = [(k, degree[i], least[root[i]], k == least[root[i]]) for i, (k, _) in enumerate(VECTORS)]
    assert degree[0] == 4  # a repeated row, an equal vector and the same direction at two scales
    assert bag(answer(spark, awkward, 3).select("vec_id", "n_links", "component_id", "kept").collect()) == bag(want)


def check_sql(spark, folder, name):
    c = duckdb.connect()
    c.sql(f"CREATE VIEW documents AS SELECT * FROM read_parquet('{folder}/documents.parquet')")
    want = c.sql(ORACLES[name])
    got = QUERIES[name](spark, folder).select(*want.columns)
    assert bag(got.collect()) == bag(want.fetchall())


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_sql_twins(spark, sf, name):
    check_sql(spark, sf, name)


def test_mixing(spark, awkward):
    rows = answer(spark, awkward, 4).collect()
    size = lambda t: len(WORD.findall(t or ""))
    assert bag((r.doc_id, r["size"]) for r in rows) == bag((k, size(t)) for k, t in ROWS)
    source = [None if i % 4 == 0 else f"s{i % 3}" for i in range(len(ROWS))]
    names = sorted(set(source), key=lambda s: (s is None, s))
    total = [sum(size(t) for s, (_, t) in zip(source, ROWS) if s == n) for n in names]
    target = brute_targets(total, [(3.0, 1.0, 2.0)[i % 3] for i in range(len(names))], 1.5, 2)
    for n, t in zip(total, target):
        mine = [r for r in rows if r.source_size == n]
        assert all(r.target == pytest.approx(t) and 0 <= r.taken <= 2 * r["size"] for r in mine)
        assert abs(sum(r.taken for r in mine) - t) <= 1
    assert bag(rows) == bag(answer(spark, awkward, 4).collect())


def test_repeats(spark, awkward):
    want = brute_removed({i: (t or "").encode() for i, (_, t) in enumerate(ROWS)}, 200)
    got = answer(spark, awkward, 5).select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")
    assert bag(got.collect()) == bag((k, *want[i]) for i, (k, _) in enumerate(ROWS))


def test_grammar_files(spark, awkward, ids):
    rows = answer(spark, awkward, 6).orderBy("start").collect()
    coded = [[*ids(t), 0] for _, t in ROWS]
    assert bag((r.doc_id, r.n_tokens, r.ids_crc32) for r in rows) == bag((k, len(v), crc(v)) for (k, _), v in zip(ROWS, coded))
    assert [r.start for r in rows] == [0, *np.cumsum([r.n_tokens for r in rows])[:-1].tolist()]
    order = [(r.doc_id is not None, r.doc_id or 0) for r in rows]
    assert order == sorted(order)


def brute_live(rows, owners, repositories):
    """For each row its spans (kind, start, end, live), as the method defines them."""
    found = [secrets.find_spans(t or "") for t in rows]
    who, where = {}, {}
    for spans, o, r in zip(found, owners, repositories):
        for *_, v in spans:
            who.setdefault(v, set()).add(o)
            where.setdefault(v, set()).add(r)
    live = lambda v: len(who[v]) < secrets.EXAMPLE_OWNERS and len(where[v]) < secrets.EXAMPLE_REPOSITORIES
    return [[(k, s, e, live(v)) for k, s, e, v in spans if k != secrets.LIVE or live(v)] for spans in found]


def sources_of(rows):
    return [None if i % 4 == 0 else f"s{i % 3}" for i in range(len(rows))], [None if i % 5 == 0 else "en" for i in range(len(rows))]


def test_secrets(spark, awkward):
    source, lang = sources_of(ROWS)
    spans = brute_live([t for _, t in ROWS], source, list(zip(source, lang)))
    want = []
    for (k, t), found in zip(ROWS, spans):
        base = brute_spans(t or "")
        n = [base.count(f"{x}:") for x in secrets.KINDS]
        want.append((k, *n, hashlib.sha256(base.encode()).hexdigest(), ",".join(f"{x}:{s}:{e}" for x, s, e, _ in found), sum(x[3] for x in found)))
    got = answer(spark, awkward, 7).select("doc_id", *[f"n_{k}" for k in secrets.KINDS], "base_sha256", "spans", "n_live")
    assert bag(got.collect()) == bag(want)


def test_base_counts_of_texts_with_spans(spark, awkward):
    """The tables of sf0.001 have no span at all; here every kind has some."""
    got = QUERIES["secret_base_counts"](spark, awkward)
    assert got.where("n_assign > 0").count() and got.where("n_access > 0").count() and got.where("n_hex > 0").count()
    want = duckdb.sql(ORACLES["secret_base_counts"].replace("FROM documents", f"FROM '{awkward}/documents.parquet/*.parquet'"))
    assert bag(got.select(*want.columns).collect()) == bag(want.fetchall())


def test_repositories_count(spark):
    rows = [(i, "token=within_one_owner1", "big", f"r{i % 5}") for i in range(10)] + [(20 + i, "token=in_two_places_22", "big", f"r{i}") for i in range(2)]
    rows += [(30, "token=null_or_not_333", None, "x"), (31, "token=null_or_not_333", "x", None)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string, repo string")
    got = {r.doc_id: r.spans[0] for r in secrets.classified_spans(df, "text", "doc_id", "source", secrets.pair_key("source", "repo")).collect()}
    assert (got[0].n_owners, got[0].n_repositories, got[0].n_found, got[0].live) == (1, 5, 10, False)
    assert (got[20].n_repositories, got[20].live) == (2, True)
    assert (got[30].n_owners, got[30].n_repositories, got[30].live) == (2, 2, True)


def test_quality(spark, awkward):
    source, lang = sources_of(ROWS)
    rows = [(t, a, b) for (_, t), a, b in zip(ROWS, lang, source)]
    failed, _, kept = reference_verdicts(rows)
    want = [(k, *brute_statistics(t)[:5], bool(f), bool(v)) for (k, t), f, v in zip(ROWS, failed, kept)]
    got = answer(spark, awkward, 8).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")
    assert bag(got.collect()) == bag(want)


def test_quality_of_given_documents(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").orderBy("doc_id").collect()
    check_verdicts(answer(spark, sf, 8).orderBy("doc_id").collect(), [(r.text, r.lang, r.source) for r in docs])


def test_shards(spark, awkward):
    rows = answer(spark, awkward, 9).collect()
    assert bag((r.doc_id, r["size"], r.text_crc32) for r in rows) == bag((k, len((t or "").encode()) + 1, zlib.crc32((t or "").encode())) for k, t in ROWS)
    per = [sorted(r.slot for r in rows if r.shard == k) for k in range(8)]
    assert all(p == list(range(len(p))) for p in per) and sum(map(len, per)) == len(ROWS)


def test_separators(spark, awkward):
    t = Tokenizer.from_file(tokenizer_path())
    t.encode_special_tokens = True
    want = [(k, len(t.encode(x or "", add_special_tokens=False).ids)) for k, x in ROWS]
    assert bag(answer(spark, awkward, 10).select("doc_id", "n_tokens").collect()) == bag(want)


def columns(df):
    return [(r.doc_id, r.text, r.lang, r.source) for r in df.collect()]


def test_stages(spark, awkward, tmp_path, ids):
    """Every stage on what its predecessor kept, each against its own brute force."""
    df = spark.read.parquet(f"{awkward}/documents.parquet")
    names = df.columns
    stages = dict(corpus_pipeline.STAGES)

    def run(name):
        nonlocal df
        before = columns(df)
        stages[name](spark, df, awkward).write.parquet(str(tmp_path / name))
        df = spark.read.parquet(str(tmp_path / name))
        assert name == "packing" or df.columns == names
        return before

    before = run("quality")
    _, _, kept = reference_verdicts([r[1:] for r in before])
    assert bag(columns(df)) == bag(r for r, k in zip(before, kept) if k)

    # what the quality rules would have taken from the awkward table comes back, for the stages to come
    df = spark.read.parquet(f"{awkward}/documents.parquet")
    before = run("near_duplicates")
    got = columns(df)
    _, least, members = brute_rows([r[:2] for r in before], 5)
    assert len(got) == len(members) and not Counter(got) - Counter(before)
    assert bag((r[0],) for r in got) == bag((least[m[0]],) for m in members)
    assert sum(r[0] is None for r in got) == sum(r[0] is None for r in before)

    df = spark.read.parquet(f"{awkward}/documents.parquet")
    before = run("secrets")
    spans = brute_live([r[1] for r in before], [r[3] for r in before], [r[2:] for r in before])
    want = []
    for r, found in zip(before, spans):
        text, shift, end = r[1], 0, 0
        for _, s, e, live in found:
            if live and s >= end:
                text = text[: s + shift] + "[secret]" + text[e + shift :]
                shift += 8 - (e - s)
                end = e
        want.append((r[0], text, *r[2:]))
    assert bag(columns(df)) == bag(want)
    assert all(r.text is None or r.n_chars == len(r.text) for r in df.collect())
    assert not any("uniquevalue" in (r[1] or "") or "otherlive" in (r[1] or "") for r in want) and any("copied_example" in (r[1] or "") for r in want)

    before = run("mixing")
    size = lambda r: len(WORD.findall(r[1] or ""))
    names_of = sorted({r[3] for r in before}, key=lambda s: (s is None, s))
    total = [sum(size(r) for r in before if r[3] == n) for n in names_of]
    target = brute_targets(total, [(3.0, 1.0, 2.0)[i % 3] for i in range(len(names_of))], 1.5, 2)
    got = columns(df)
    assert not set(got) - set(before)
    for n, t in zip(names_of, target):
        assert abs(sum(size(r) for r in got if r[3] == n) - t) <= max(size(r) for r in before if r[3] == n) / 2 + 1
    assert all(c <= 2 * Counter(before)[r] for r, c in Counter(got).items() if size(r))

    before = run("packing")
    check_pieces(df.collect(), [(r[0], [*ids(r[1]), 1]) for r in before])


def test_stages_of_nothing(spark, empty):
    df = spark.read.parquet(f"{empty}/documents.parquet")
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, df, empty)
        assert out.count() == 0 and (name == "packing" or out.columns == df.columns)


def test_nothing_is_left_but_results(spark, sf):
    import os

    from freqsketch.llm.common import shared_root

    folder = shared_root(spark).removeprefix("file://")
    before = set(os.listdir(folder))
    answer(spark, sf, 10).count()
    assert len(set(os.listdir(folder)) - before) == 1
