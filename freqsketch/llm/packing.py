"""Lexical retrieval packing (operator 1): windows filled by BM25 neighbours of their seed."""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import mix64, new_shared_dir, numbered, read_table, segment_hash, settled, tidy, written
from .positions import with_positions, write_positions
from .shared_files import atomic_writer, open_store
from .sharding import byte_prefix_shards
from .tokens import encoder, id_type, tokenizer_path, with_ids

WINDOW = 2048
#: Fixed value: the id that ends a document.
END_ID = 1
K1, B = 1.2, 0.75
#: Index terms are words, hashed into so many terms; corpus statistics are a vector of this
#: length whatever the corpus.
TERM_BITS = 20
#: Most documents and ids in a shard of the index.
SHARD_DOCS = 1024
SHARD_IDS = 4 << 20
#: Dimensions in which documents are placed by their words, the leaves of the tree that orders
#: places, and the groups, a bounded sample of about so many, that the tree is fitted to.
PLACE_DIMS = 8
LEAVES = 256
FIT_GROUPS = 16384

PIECE_SCHEMA = (
    "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
)


@cache
def _word_marks(path: str) -> np.ndarray:
    """True for ids that begin a word: their bytes begin with a space or a line end."""
    enc = encoder(path)
    marks = np.zeros(1 << 16 if enc.words.get_vocab_size() <= 1 << 16 else enc.words.get_vocab_size(), bool)
    space, line = enc.alphabet[32], enc.alphabet[10]
    for i in range(enc.words.get_vocab_size()):
        t = enc.words.id_to_token(i) or ""
        marks[i] = t[:1] in (space, line)
    return marks


def document_terms(ids: np.ndarray, lengths: np.ndarray, marks: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, term, times) of the words of documents given as joined ids, by row, then term."""
    if not len(ids):
        z = np.zeros(0, np.int64)
        return z, z, z
    begin = marks[ids]
    ends = np.cumsum(lengths)
    firsts = (ends - lengths)[lengths > 0]
    begin[firsts] = True
    starts = np.flatnonzero(begin)
    rows = np.searchsorted(ends, starts, "right")
    h = segment_hash(ids, starts, np.append(starts[1:], len(ids)))
    term = (h >> np.uint64(64 - TERM_BITS)).astype(np.int64)
    pair, times = np.unique((rows << TERM_BITS) | term, return_counts=True)
    return pair >> TERM_BITS, pair & ((1 << TERM_BITS) - 1), times


class _Frequencies:
    """Counts, in one task, of documents by the terms they hold; a file of (term, count) at the end."""

    def __init__(self, folder: str, path: str):
        self.folder, self.marks = folder, _word_marks(path)
        self.counts = np.zeros(1 << TERM_BITS, np.int64)

    def add(self, ids: np.ndarray, lengths: np.ndarray) -> None:
        self.counts += np.bincount(document_terms(ids, lengths, self.marks)[1], minlength=len(self.counts))

    def close(self) -> None:
        at = np.flatnonzero(self.counts)
        with atomic_writer(f"{self.folder}/{TaskContext.get().partitionId()}.bin") as out:
            out.write(np.stack([at, self.counts[at]]).astype("<i8").tobytes())


def document_frequencies(spark: SparkSession, folder: str) -> np.ndarray:
    """Number of documents of the whole corpus that hold each hashed term, from the tasks' files.

    They are added by tasks; at most 2^TERM_BITS sums reach the driver."""

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        df = np.zeros(1 << TERM_BITS, np.int64)
        for b in batches:
            for raw in b.column(0).to_pylist():
                term, n = np.frombuffer(raw, "<i8").reshape(2, -1)
                df[term] += n
        at = np.flatnonzero(df)
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(df[at])], ["term", "n"])

    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.bin").load(folder).select("content")
    sums = files.mapInArrow(tidy(add), "term int, n long").groupBy("term").agg(F.sum("n").alias("n")).toArrow()
    out = np.zeros(1 << TERM_BITS, np.int64)
    out[sums.column("term").to_numpy()] = sums.column("n").to_numpy()
    return out


#: Rank of a term that no two documents share.
LONE = 1 << 30
#: How much more a rare term counts than a common one in the choice of a document's group.
RARITY = 4


def term_ranks(counts: np.ndarray, n_docs: int) -> np.ndarray:
    """A fixed random order of the terms in which rare ones tend to come first: of the terms of a
    document the first is a weighted min-hash, so two documents have the same first term with a
    chance that is their shared weight. Terms that no two documents share have the rank LONE."""
    u = ((mix64(np.arange(len(counts), dtype=np.uint64) + np.uint64(99)) >> np.uint64(11)).astype(np.float64) + 0.5) / 2**53
    late = -np.log(u) / np.log1p((n_docs - counts + 0.5) / (counts + 0.5)) ** RARITY
    rank = np.empty(len(counts), np.int32)
    rank[np.argsort(late, kind="stable")] = np.arange(len(counts), dtype=np.int32)
    return np.where(counts > 1, rank, LONE).astype(np.int32)


@cache
def _term_signs() -> np.ndarray:
    """(terms, PLACE_DIMS) of 1 and -1: a fixed random projection of the space of terms."""
    bits = mix64(np.arange(1 << TERM_BITS, dtype=np.uint64) + np.uint64(1 << 40))
    return (1 - 2 * ((bits[:, None] >> np.arange(PLACE_DIMS, dtype=np.uint64)) & np.uint64(1)).astype(np.int8)).astype(np.float32)


def content_keys(row: np.ndarray, term: np.ndarray, weight: np.ndarray, ranks: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Where documents belong: (near, place). ``near`` is the rank of a document's first shared term
    in the order of ``term_ranks``, -1 where it shares none. ``place`` is the direction of its
    weighted terms in PLACE_DIMS random dimensions."""
    near, place = np.full(n, -1, np.int64), np.zeros((n, PLACE_DIMS), np.float32)
    if not len(row):
        return near, place
    begin = np.flatnonzero(np.diff(row, prepend=-1))
    own = row[begin]
    least = np.minimum.reduceat(ranks[term], begin)
    near[own] = np.where(least < LONE, least, -1)
    place[own] = np.add.reduceat(_term_signs()[term] * weight[:, None].astype(np.float32), begin)
    return near, place / np.maximum(np.sqrt((place * place).sum(1, keepdims=True)), 1e-12)


def fit_tree(points: np.ndarray, leaves: int) -> list[tuple[np.ndarray, float]]:
    """A complete binary tree, its nodes level by level: a direction and a threshold each. Every
    node halves its points along their principal axis, so neighbouring leaves hold like points."""
    nodes, level = [], [np.arange(len(points))]
    while len(level) < leaves:
        below = []
        for at in level:
            x = points[at]
            centred = x - x.mean(0) if len(x) else x
            axis = np.linalg.eigh(centred.T @ centred)[1][:, -1]
            axis = axis * (1.0 if axis[np.argmax(np.abs(axis))] > 0 else -1.0)
            along = x @ axis
            cut = float(np.median(along)) if len(x) else 0.0
            nodes.append((axis, cut))
            below += [at[along <= cut], at[along > cut]]
        level = below
    return nodes


def leaf_of(points: np.ndarray, nodes: list[tuple[np.ndarray, float]]) -> np.ndarray:
    """Number of the leaf of each point."""
    at = np.zeros(len(points), np.int64)
    axes = np.array([a for a, _ in nodes]).reshape(len(nodes), -1)
    cuts = np.array([c for _, c in nodes])
    first, width = 0, 1
    while first < len(nodes):
        node = first + at
        at = 2 * at + ((points * axes[node]).sum(1) > cuts[node])
        first, width = first + width, 2 * width
    return at


class ShardIndex:
    """Inverted index of one shard's documents, with the corpus's statistics."""

    def __init__(self, ids, lengths, marks, idf, mean_length):
        row, term, times = document_terms(ids, lengths, marks)
        self.n = len(lengths)
        weight = bm25(row, term, times, lengths, idf, mean_length)
        by_term = np.argsort((term << max(1, self.n.bit_length())) | row)
        self.rows, self.weights = row[by_term], weight[by_term]
        self.row_begin = np.searchsorted(row, np.arange(self.n + 1))
        ordered = term[by_term]
        first = np.flatnonzero(np.diff(ordered, prepend=-1))
        slot = np.empty(len(term), np.int64)
        slot[by_term] = np.repeat(np.arange(len(first)), np.diff(first, append=len(term)))
        self.post_begin, self.post_n = first[slot], np.diff(first, append=len(term))[slot]

    def scores(self, doc: int) -> np.ndarray:
        """BM25 of every document of the shard for the words of one of them."""
        lo, hi = self.row_begin[doc], self.row_begin[doc + 1]
        n = self.post_n[lo:hi]
        if not len(n):
            return np.zeros(self.n)
        ends = np.cumsum(n)
        at = np.arange(ends[-1]) + np.repeat(self.post_begin[lo:hi] - (ends - n), n)
        return np.bincount(self.rows[at], weights=self.weights[at], minlength=self.n)


def bm25(row, term, times, lengths, idf, mean_length) -> np.ndarray:
    """Weight of each (document, term), by document length in ids."""
    norm = K1 * (1 - B + B * lengths / max(mean_length, 1e-9))
    return idf[term] * times * (K1 + 1) / (times + norm[row])


def pack_shard(index: ShardIndex, lengths: np.ndarray, window: int) -> Iterator[tuple[int, int, int, int, int]]:
    """(document, start, length, sequence, offset): every document, cut where a window ends.

    What a window leaves over of its last document is the next one's seed; else the first
    unused document is. A seed's unused neighbours follow by falling score, then by place.
    """
    used = lengths == 0
    fresh = 0
    sequence, room = 0, window
    doc, start = -1, 0
    while True:
        if doc < 0:
            while fresh < len(lengths) and used[fresh]:
                fresh += 1
            if fresh == len(lengths):
                return
            doc, start = fresh, 0
            used[doc] = True
        ranked: list[int] | None = None
        while True:
            take = min(room, int(lengths[doc]) - start)
            yield doc, start, take, sequence, window - room
            start += take
            room -= take
            if room == 0:
                sequence, room = sequence + 1, window
                doc, start = (doc, start) if start < lengths[doc] else (-1, 0)
                break
            if ranked is None:
                score = index.scores(doc)
                score[used] = -1.0
                good = np.flatnonzero(score > 0)
                ranked = good[np.lexsort((-good, score[good]))].tolist()
            doc, start = -1, 0
            if not ranked:
                break
            doc = ranked.pop()
            used[doc] = True


def _slices(values: list[bytes], kind: np.dtype, docs: int = 512) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(first row, ids, lengths) of a batch of documents, a bounded number at a time."""
    for lo in range(0, len(values), docs):
        part = values[lo : lo + docs]
        yield lo, np.frombuffer(b"".join(part), kind), np.array([len(v) // kind.itemsize for v in part], np.int64)


def deal_by_content(tokens: DataFrame, path: str, counts: np.ndarray, idf, mean_length: float, n_docs: int, n_ids: int, shard_docs: int = SHARD_DOCS) -> DataFrame:
    """(_n, shard) of every document: like documents meet in one shard of bounded size.

    Documents with the same weighted min-hash of their shared terms form a group; a group's mean
    place says which leaf of a principal-axis tree it is in. Documents in the order of leaf, group and number are
    cut into contiguous shards of at most about ``shard_docs`` documents and SHARD_IDS ids. A group
    of any size is cut like the rest. Only narrow rows travel here."""
    spark = tokens.sparkSession
    sent = spark.sparkContext.broadcast(term_ranks(counts, n_docs))
    dims = [f"_v{i}" for i in range(PLACE_DIMS)]

    def keys(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        marks, kind = _word_marks(path), id_type(path)
        for b in batches:
            for lo, ids, lengths in _slices(b.column(1).to_pylist(), kind):
                row, term, times = document_terms(ids, lengths, marks)
                near, place = content_keys(row, term, bm25(row, term, times, lengths + 1, idf.value, mean_length), sent.value, len(lengths))
                number = b.column(0).slice(lo, len(lengths))
                lone = near < 0  # a document that shares nothing is a group of its own
                near[lone] = -1 - number.to_numpy()[lone]
                yield pa.RecordBatch.from_arrays(
                    [number, pa.array(near), pa.array(lengths + 1), *[pa.array(place[:, i].astype(np.float32)) for i in range(PLACE_DIMS)]], ["_n", "_near", "_len", *dims]
                )

    schema = "_n long, _near long, _len long, " + ", ".join(f"{d} float" for d in dims)
    keyed = written(tokens.select("_n", "ids").mapInArrow(tidy(keys), schema), "packing-keys")
    groups = written(keyed.groupBy("_near").agg(*[F.avg(d).alias(d) for d in dims]), "packing-groups")
    # about FIT_GROUPS of the groups, by a hash; the order that follows holds all of them
    share = min(1.0, FIT_GROUPS / max(1, groups.count()))
    drawn = F.xxhash64(F.lit(7), "_near").bitwiseAND((1 << 30) - 1) < int(share * (1 << 30))
    sample = groups.where(drawn).toArrow().sort_by("_near")
    nodes = fit_tree(np.stack([sample.column(d).to_numpy() for d in dims], 1), LEAVES)

    def leaves(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            at = leaf_of(np.stack([b.column(i + 1).to_numpy() for i in range(PLACE_DIMS)], 1), nodes)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(at)], ["_near", "_leaf"])

    # written as they are joined: a group of very many documents is split by the adaptive join
    placed = written(keyed.select("_n", "_near", "_len").join(groups.mapInArrow(leaves, "_near long, _leaf long"), "_near"), "packing-places")
    # in units of which a shard holds shard_docs * SHARD_IDS
    size = F.col("_len") * shard_docs + SHARD_IDS
    n_shards = max(1, -(-(n_ids * shard_docs + n_docs * SHARD_IDS) // (shard_docs * SHARD_IDS)))
    order = [F.col("_leaf"), F.col("_near"), F.col("_n")]
    return byte_prefix_shards(placed, order, size, n_shards, {"_n": F.col("_n")}).select("_n", F.col("shard"))


def pack_documents(
    df: DataFrame, text: str, key: str, path: str, window: int = WINDOW, end_id: int = END_ID, ids_too: bool = True, shard_docs: int = SHARD_DOCS
) -> DataFrame:
    """Pieces of all documents, packed into sequences of ``window`` ids.

    Documents (whole texts' ids and ``end_id``) are dealt by content into shards of a bounded size
    (``deal_by_content``); each shard is an inverted index in the memory of one task and is packed
    there. Term weights use document frequencies, document count and mean length of the whole
    corpus. A neighbour is looked for in the seed's own shard. Only a shard's last sequence can be
    short. Returns PIECE_SCHEMA and, with ``ids_too``, the piece's ids as little-endian unsigned
    32-bit integers.

    Null and empty texts are documents of ``end_id`` alone. Rows with equal or null keys are packed
    each for itself; equal scores go by key, then by the order of the input. An empty table gives no
    pieces. Other columns of the input are ignored.
    """
    spark = df.sparkSession
    schema = PIECE_SCHEMA + (", ids binary" if ids_too else "")
    counted = new_shared_dir(spark, "packing-terms")
    store, where = open_store(counted)
    store.create_dir(where, recursive=True)
    texts = df.select(F.col(key).cast("long").alias("doc_id"), F.col(text).alias("_t"))
    coded = with_ids(texts, "_t", ["doc_id"], path, watch=lambda: _Frequencies(counted, path))
    tokens = numbered(coded, "_n", "packing-ids", keep=True)
    width = id_type(path).itemsize
    stats = tokens.agg(F.count("*").alias("n"), F.sum(F.length("ids") / width + 1).alias("ids")).first()
    n_docs, n_ids = stats["n"], int(stats["ids"] or 0)
    if not n_docs:
        return spark.createDataFrame([], schema)
    counts = document_frequencies(spark, counted)
    idf = spark.sparkContext.broadcast(np.log1p((n_docs - counts + 0.5) / (counts + 0.5)).astype(np.float32))
    mean_length = n_ids / n_docs
    folder = write_positions(deal_by_content(tokens, path, counts, idf, mean_length, n_docs, n_ids, shard_docs), "packing-shards")

    def pack(table: pa.Table) -> pa.Table:
        table = table.sort_by([("doc_id", "ascending"), ("_n", "ascending")])
        number = table.column("shard")[0].as_py()
        kind = id_type(path)
        end = np.array([end_id], kind).tobytes()
        values = [v + end for v in table.column("ids").to_pylist()]
        lengths = np.array([len(v) // kind.itemsize for v in values], np.int64)
        ids = np.frombuffer(b"".join(values), kind)
        index = ShardIndex(ids, lengths, _word_marks(path), idf.value, mean_length)
        keys = table.column("doc_id").to_pylist()
        wide = ids.astype("<u4")
        raw = memoryview(wide.tobytes())
        first = np.cumsum(lengths) - lengths
        rows = []
        for doc, start, n, seq, offset in pack_shard(index, lengths, window):
            at = int(first[doc]) + start
            piece = raw[4 * at : 4 * (at + n)]
            row = (keys[doc], start, n, zlib.crc32(piece), int(lengths[doc]), (number << 32) | seq, offset)
            rows.append((*row, bytes(piece)) if ids_too else row)
        names = [f.split()[0] for f in schema.split(", ")]
        kinds = [pa.int64()] * 7 + [pa.binary()] * ids_too
        return pa.Table.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], names)

    return with_positions(tokens, "_n", folder, "shard").groupBy("shard").applyInArrow(tidy(pack), schema)


@settled
def op1_retrieval_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pieces of every document; see ``pack_documents``."""
    docs = read_table(spark, sf_dir, "documents")
    return pack_documents(docs, "text", "doc_id", tokenizer_path(), ids_too=False)
