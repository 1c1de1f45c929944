"""Token files compressed with a grammar of repeated pairs (operator 6)."""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import new_shared_dir, read_table, settled, tidy, written
from .shared_files import atomic_writer, open_store, read_range
from .tokens import id_type, tokenizer_path, with_ids

END_ID = 0
#: Ids of a block; each block has a grammar of its own and can be decoded alone.
BLOCK_IDS = 1 << 20
#: Bytes of text for each file.
FILE_BYTES = 256 << 20
#: A rule takes two symbols and a 32-bit length; a pair that occurs so often repays that, for every
#: occurrence saves a symbol of 16 bits or more.
LEAST_COUNT = 5
#: A pass replaces the pairs that occur at least this share as often as its most frequent one.
PASS_SHARE = 0.05
SLOT_BITS = 18
MAGIC = b"RPR2"
HEAD = struct.Struct("<4sIQQQIII")


def _slot(keys: np.ndarray) -> np.ndarray:
    return ((keys * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - SLOT_BITS)).astype(np.int64)


def _frequent_pairs(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pairs that occur LEAST_COUNT times or more, and how often. A small table of counts of hashes
    rules out most of the rare ones before anything is sorted."""
    slot = _slot(keys)
    s = np.sort(keys[np.bincount(slot, minlength=1 << SLOT_BITS)[slot] >= LEAST_COUNT])
    if not len(s):
        return s, np.zeros(0, np.int64)
    edge = np.concatenate([[0], np.flatnonzero(s[1:] != s[:-1]) + 1])
    counts = np.diff(edge, append=len(s))
    often = counts >= LEAST_COUNT
    return s[edge[often]], counts[often]


def compress(ids: np.ndarray, lengths: np.ndarray, first_symbol: int) -> dict[str, np.ndarray]:
    """Grammar of one block: ``rules`` (left, right), ``expanded`` (ids under each rule),
    ``symbols`` and, for each document, its number of symbols.

    Every pass counts all neighbouring pairs, gives the most frequent ones a new symbol each
    and replaces their occurrences from the left; where occurrences overlap every second one
    of the chain is taken. Passes go on until no pair repays its rule. A pair never spans two
    documents, so each can be decoded alone.
    """
    s = ids.astype(np.uint64)
    last = np.zeros(len(s), bool)
    last[np.cumsum(lengths)[lengths > 0] - 1] = True
    rules: list[np.ndarray] = []
    symbol = first_symbol
    while len(s) > 1:
        keys = (s[:-1] << np.uint64(32)) | s[1:]
        inner = ~last[:-1]
        pairs, counts = _frequent_pairs(keys[inner])
        if not len(pairs):
            break
        often = np.flatnonzero(counts >= max(LEAST_COUNT, PASS_SHARE * counts.max()))
        often = often[np.argsort(-counts[often], kind="stable")]
        # one pair for each slot of a small table, the most frequent one; the others wait for a later pass
        _, one = np.unique(_slot(pairs[often]), return_index=True)
        chosen = pairs[often[np.sort(one)]]
        table = np.zeros(1 << SLOT_BITS, np.uint64)
        to = np.zeros(1 << SLOT_BITS, np.uint64)
        slot = _slot(chosen)
        table[slot] = chosen
        to[slot] = np.arange(symbol, symbol + len(chosen), dtype=np.uint64)
        at = _slot(keys)
        hit = np.flatnonzero((table[at] == keys) & (to[at] > 0) & inner)
        # chains of hits that follow one another: keep the first, third, ...
        head = np.ones(len(hit), bool)
        head[1:] = hit[1:] != hit[:-1] + 1
        begin = np.flatnonzero(head)
        rank = np.arange(len(hit)) - np.repeat(begin, np.diff(begin, append=len(hit)))
        hit = hit[rank % 2 == 0]
        s[hit] = to[at[hit]]
        last[hit] = last[hit + 1]
        stay = np.ones(len(s), bool)
        stay[hit + 1] = False
        s, last = s[stay], last[stay]
        rules.append(np.stack([chosen >> np.uint64(32), chosen & np.uint64(0xFFFFFFFF)], 1))
        symbol += len(chosen)
    table = np.concatenate(rules).astype("<u4") if rules else np.zeros((0, 2), "<u4")
    expanded = np.ones(symbol, np.int64)
    at = first_symbol
    for r in rules:  # a pass refers to symbols of earlier passes only
        expanded[at : at + len(r)] = expanded[r[:, 0].astype(np.int64)] + expanded[r[:, 1].astype(np.int64)]
        at += len(r)
    n_symbols = np.zeros(len(lengths), np.int64)
    n_symbols[lengths > 0] = np.diff(np.flatnonzero(last) + 1, prepend=0)
    return {"rules": table, "expanded": expanded[first_symbol:].astype("<u4"), "symbols": s.astype("<u4"), "n_symbols": n_symbols.astype("<u4")}


def expand(symbols: np.ndarray, rules: np.ndarray, expanded: np.ndarray, first_symbol: int, start: int = 0, stop: int | None = None) -> np.ndarray:
    """Ids ``start`` to ``stop`` of what a run of symbols stands for. The lengths under the rules say
    which symbols reach into the range; only those are taken apart, all at once, level by level."""
    size = np.concatenate([np.ones(first_symbol, np.int64), expanded.astype(np.int64)])
    left, right = (np.concatenate([np.zeros(first_symbol, np.int64), rules[:, k].astype(np.int64)]) for k in (0, 1))
    s = symbols.astype(np.int64)
    at = np.cumsum(size[s]) - size[s]
    stop = int(size[s].sum()) if stop is None else stop
    out = np.zeros(max(0, stop - start), np.uint32)
    while len(s):
        reach = (at < stop) & (at + size[s] > start)
        s, at = s[reach], at[reach]
        plain = s < first_symbol
        out[at[plain] - start] = s[plain]
        s, at = s[~plain], at[~plain]
        a, b = left[s], right[s]
        s, at = np.concatenate([a, b]), np.concatenate([at, at + size[a]])
    return out


def _packed(values: np.ndarray, bits: int) -> bytes:
    """Numbers of so many bits each, one after the other."""
    out = bytearray()
    for lo in range(0, len(values), 1 << 17):  # a multiple of 8 numbers fills whole bytes
        part = values[lo : lo + (1 << 17)].astype(">u4")
        out += np.packbits(np.unpackbits(part.view(np.uint8).reshape(-1, 4), axis=1)[:, 32 - bits :]).tobytes()
    return bytes(out)


def _unpacked(raw: np.ndarray, bits: int, first: int, count: int) -> np.ndarray:
    """``count`` numbers of so many bits each from the ``first`` on."""
    at = (first + np.arange(count, dtype=np.int64)) * bits
    padded = np.concatenate([raw, np.zeros(8, np.uint8)])
    word = np.zeros(count, np.uint64)
    for k in range(5):
        word = (word << np.uint64(8)) | padded[(at >> 3) + k]
    return ((word >> (np.uint64(40 - bits) - (at & 7).astype(np.uint64))) & np.uint64((1 << bits) - 1)).astype(np.uint32)


def pack_block(keys: list[int | None], lengths: np.ndarray, ids: np.ndarray, first_symbol: int) -> bytes:
    """A block as bytes: a head; keys, where they are null, documents' lengths in ids and in symbols;
    rules and the lengths under them; symbols of as few bits as tell them apart."""
    g = compress(ids, lengths, first_symbol)
    bits = max(1, int(first_symbol + len(g["rules"]) - 1).bit_length())
    head = HEAD.pack(MAGIC, first_symbol, len(keys), len(ids), len(g["symbols"]), len(g["rules"]), bits, 0)
    blank = np.array([k is None for k in keys], np.uint8)
    plain = np.array([k or 0 for k in keys], "<i8")
    parts = [plain, blank, lengths.astype("<u4"), g["n_symbols"], g["expanded"]]
    return head + b"".join(p.tobytes() for p in parts) + _packed(g["rules"].ravel(), bits) + _packed(g["symbols"], bits)


class Block:
    """A block as written; documents can be decoded together or one by one."""

    def __init__(self, raw: bytes):
        magic, self.first, n, self.n_ids, n_symbols, n_rules, self.bits, _ = HEAD.unpack_from(raw)
        if magic != MAGIC:
            raise ValueError("not a block of a token file")
        at = HEAD.size

        def take(kind: str, count: int) -> np.ndarray:
            nonlocal at
            out = np.frombuffer(raw, kind, count, at)
            at += out.nbytes
            return out

        plain, blank = take("<i8", n), take("u1", n)
        self.keys = [None if b else k for k, b in zip(plain.tolist(), blank.tolist())]
        self.lengths, self.n_symbols, self.expanded = take("<u4", n), take("<u4", n), take("<u4", n_rules)
        self.rules = _unpacked(take("u1", -(-2 * n_rules * self.bits // 8)), self.bits, 0, 2 * n_rules).reshape(-1, 2)
        self.packed = take("u1", -(-n_symbols * self.bits // 8))

    def _expand(self, first: int, count: int, start: int = 0, stop: int | None = None) -> np.ndarray:
        return expand(_unpacked(self.packed, self.bits, first, count), self.rules, self.expanded, self.first, start, stop)

    def ids(self) -> np.ndarray:
        return self._expand(0, int(self.n_symbols.sum(dtype=np.int64)))

    def document(self, i: int, start: int = 0, stop: int | None = None) -> np.ndarray:
        """Ids ``start`` to ``stop`` of the i-th document; no other document is taken apart."""
        stop = int(self.lengths[i]) if stop is None else min(stop, int(self.lengths[i]))
        return self._expand(int(self.n_symbols[:i].sum(dtype=np.int64)), int(self.n_symbols[i]), start, stop)


def read_document(folder: str, file: str, at: int, n_bytes: int, i: int, start: int = 0, stop: int | None = None) -> np.ndarray:
    """Ids of the i-th document of a block that the index of ``write_grammar_files`` names."""
    return Block(read_range(f"{folder}/{file}", at, n_bytes)).document(i, start, stop)


def key_bounds(df: DataFrame, key: str, n: int) -> list[int]:
    """Distinct upper bounds of at most n near-equal ranges of a bigint key, by approximate
    quantiles; n numbers reach the driver. More than a range's share of rows with one key
    stay in one range."""
    shares = [(i + 1) / n for i in range(n - 1)]
    if not shares:
        return []
    got = df.agg(F.percentile_approx(F.col(key).cast("long"), shares, 10_000)).first()[0]
    return sorted(set(got or []))


def range_number(key: Column, bounds: list[int]) -> Column:
    """Number of bounds below the key, by halving."""
    if not bounds:
        return F.lit(0)
    mid = len(bounds) // 2
    low, high = bounds[:mid], bounds[mid + 1 :]
    return F.when(key > bounds[mid], range_number(key, high) + mid + 1).otherwise(range_number(key, low))


def write_grammar_files(df: DataFrame, text: str, key: str, folder: str, path: str, end_id: int = END_ID, parts: int | None = None) -> DataFrame:
    """Write each text's ids and ``end_id`` in ascending order of a bigint key.

    One file for each range of keys, about FILE_BYTES of text or ``parts`` files, named so that files
    in order of name hold keys in order; a file is a row of blocks. Returns one row for each block:
    (file, block, at, bytes, n_docs, n_ids). Null and empty texts are ``end_id`` alone. Equal keys
    stay together in arbitrary order; null keys come first and are marked as such. Other columns
    are ignored.
    """
    spark = df.sparkSession
    from .tokens import encoder

    first_symbol = encoder(path).words.get_vocab_size()
    ids = with_ids(df.withColumn("_key", F.col(key).cast("long")), text, ["_key"], path)
    n = parts
    if n is None:
        total = df.agg(F.sum(F.octet_length(F.col(text)).cast("long"))).first()[0] or 0
        n = max(2 * spark.sparkContext.defaultParallelism, -(-int(total) // FILE_BYTES))
    # ranges come from the keys alone: a range partitioning of the rows would make the ids twice
    bounds = key_bounds(df, key, n)
    number = F.when(F.col("_key").isNull(), 0).otherwise(range_number(F.col("_key"), bounds))
    ordered = ids.repartitionById(len(bounds) + 1, number).sortWithinPartitions(F.asc_nulls_first("_key"))
    kind = id_type(path)

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        name = f"grammar-{TaskContext.get().partitionId():06d}.bin"
        rows: list[dict] = []
        held: list[tuple[int | None, bytes]] = []
        held_ids = at = 0
        end = np.array([end_id], kind).tobytes()

        def flush(out):
            nonlocal held, held_ids, at
            lengths = np.array([len(v) // kind.itemsize + 1 for _, v in held], np.int64)
            block = pack_block([k for k, _ in held], lengths, np.frombuffer(b"".join(v + end for _, v in held), kind), first_symbol)
            out.write(block)
            rows.append({"file": name, "block": len(rows), "at": at, "bytes": len(block), "n_docs": len(held), "n_ids": int(lengths.sum())})
            at += len(block)
            held, held_ids = [], 0

        with atomic_writer(f"{folder}/{name}") as out:
            for b in batches:
                for k, v in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                    held.append((k, v))
                    held_ids += len(v) // kind.itemsize + 1
                    if held_ids >= BLOCK_IDS:
                        flush(out)
            if held:
                flush(out)
        if rows:
            yield pa.RecordBatch.from_pylist(rows)

    return ordered.select("_key", "ids").mapInArrow(tidy(write), "file string, block long, at long, bytes long, n_docs long, n_ids long")


def read_grammar_files(index: DataFrame, folder: str) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32, file) of every document, decoded from the files.

    ``start``: ids of all documents before it, from a running sum over the blocks' totals,
    one row a block. The digest is of the ids as unsigned 32-bit integers."""
    from pyspark.sql import Window as W

    by_file = index.groupBy("file").agg(F.sum("n_ids").alias("_all"))
    before = by_file.select("file", F.coalesce(F.sum("_all").over(W.orderBy("file").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("_file0"))
    inner = W.partitionBy("file").orderBy("block").rowsBetween(W.unboundedPreceding, -1)
    plan = index.join(before, "file").select(
        "file", "block", "at", "bytes", (F.col("_file0") + F.coalesce(F.sum("n_ids").over(inner), F.lit(0))).alias("start")
    )
    # blocks are tiny rows but much work: their number, not their bytes, says how many tasks
    plan = plan.repartition(max(1, min(index.count(), 4096)), "file", "block")

    def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for r in b.to_pylist():
                block = Block(read_range(f"{folder}/{r['file']}", r["at"], r["bytes"]))
                ids = block.ids().astype("<u4")
                ends = np.cumsum(block.lengths, dtype=np.int64)
                raw = memoryview(ids.tobytes())
                crc = [zlib.crc32(raw[4 * (e - n) : 4 * e]) for e, n in zip(ends.tolist(), block.lengths.tolist())]
                yield pa.RecordBatch.from_arrays(
                    [pa.array(block.keys, pa.int64()), pa.array(ends - block.lengths + r["start"]), pa.array(block.lengths.astype(np.int64)),
                     pa.array(crc, pa.int64()), pa.array([r["file"]] * len(crc))],
                    ["doc_id", "start", "n_tokens", "ids_crc32", "file"],
                )

    return plan.mapInArrow(tidy(decode), "doc_id long, start long, n_tokens long, ids_crc32 long, file string")


@settled
def op6_pair_grammar(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Digests of every document's ids, decoded from grammar files of the whole table."""
    docs = read_table(spark, sf_dir, "documents")
    folder = new_shared_dir(spark, "grammar")
    store, where = open_store(folder)
    store.create_dir(where, recursive=True)
    index = written(write_grammar_files(docs, "text", "doc_id", folder, tokenizer_path()), "grammar-index")
    return read_grammar_files(index, folder)
