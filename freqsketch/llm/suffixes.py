"""Removal of byte strings that occur more than once, by suffix arrays (operator 5).

Every string of LENGTH bytes has an anchor: the 50 bytes of it with the smallest hash. Equal
strings have equal anchors at equal places, so just strings whose anchor occurs again need a
comparison, and the anchor's hash says which shard they meet in. There, a suffix array over
the surroundings of the anchors decides. Nothing is lost by the anchors: they only keep
strings apart that differ.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import byte_slices, mix64, numbered, read_table, salted_powers, settled, text_buffer, tidy, written

#: Fixed value: bytes of a string that is removed if it starts anywhere else too.
LENGTH = 200
GRAM = 50
#: Bytes of surroundings in a shard of the suffix arrays.
SHARD_BYTES = 2 << 20
#: An anchor with more different surroundings than this is dealt over several shards.
HOT = 4096

_BASE = 0x9E3779B97F4A7C15
_TABLE = salted_powers(256, 77)


@cache
def _base_powers(bits: int) -> tuple[np.ndarray, np.ndarray]:
    out = []
    for base in (_BASE, pow(_BASE, -1, 1 << 64)):
        p = np.full(1 << bits, base, np.uint64)
        p[0] = 1
        out.append(np.multiply.accumulate(p))
    return out[0], out[1]


class RollingHash:
    """64-bit hashes of any substrings of a byte array, from prefix sums."""

    def __init__(self, raw: np.ndarray):
        n = len(raw)
        up, self.down = _base_powers(max(16, int(n + 1).bit_length()))
        self.sums = np.zeros(n + 1, np.uint64)
        np.cumsum(_TABLE[raw] * up[:n], out=self.sums[1:])

    def of(self, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        return mix64((self.sums[ends] - self.sums[starts]) * self.down[starts])

    def grams(self, width: int) -> np.ndarray:
        m = len(self.sums) - width
        return mix64((self.sums[width:] - self.sums[:m]) * self.down[:m])


def _sliding_min(x: np.ndarray, width: int) -> np.ndarray:
    k = 1
    while 2 * k <= width:
        x = np.minimum(x[:-k], x[k:])
        k *= 2
    if k < width:
        x = np.minimum(x[: len(x) - (width - k)], x[width - k :])
    return x


def anchors(raw: np.ndarray, offsets: np.ndarray, length: int = LENGTH) -> dict[str, np.ndarray]:
    """Anchors of all strings of ``length`` bytes that lie in one row.

    Per anchor: ``row``, ``at`` (its place), ``lo`` (start of the first string whose anchor it
    is), ``n`` (how many strings, one byte apart), ``gram`` and ``around``: hashes of the anchor
    and of all the bytes of its strings with the anchor's place among them."""
    n = len(raw)
    names = ("row", "at", "lo", "n", "gram", "around")
    if n < length:
        return {k: np.zeros(0, np.uint64 if k in ("gram", "around") else np.int64) for k in names}
    roll = RollingHash(raw)
    gram = roll.grams(GRAM)
    key = (gram & np.uint64(0xFFFFFFFF00000000)) | np.arange(len(gram), dtype=np.uint64)
    best = (_sliding_min(key, length - GRAM + 1) & np.uint64(0xFFFFFFFF)).astype(np.int64)
    starts = np.arange(len(best))
    row_end = np.repeat(offsets[1:], np.diff(offsets))
    starts = starts[starts + length <= row_end[: len(best)]]
    best = best[starts]
    fresh = np.ones(len(starts), bool)
    fresh[1:] = (best[1:] != best[:-1]) | (starts[1:] != starts[:-1] + 1)
    first = np.flatnonzero(fresh)
    lo, at, many = starts[first], best[first], np.diff(first, append=len(starts))
    around = roll.of(lo, lo + many - 1 + length) ^ mix64(((at - lo) * 4096 + many).astype(np.uint64))
    row = np.searchsorted(offsets, lo, "right") - 1
    return {"row": row, "at": at - offsets[row], "lo": lo - offsets[row], "n": many, "gram": gram[at], "around": around}


def suffix_array(text: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(sa, words) of many segments at once: ``text`` joined, ``ends[i]`` the end of the segment
    that position i is in. Suffixes stop at their segment's end, shorter ones come first,
    equal ones by place. Groups that are not yet in order are refined by the ranks of the
    suffixes that follow them, with doubled lengths. ``words``: 8 bytes from each position.
    """
    n = len(text)
    padded = np.concatenate([text, np.zeros(16, np.uint8)])
    words = np.zeros(n + 8, np.uint64)
    for k in range(8):
        words = (words << np.uint64(8)) | padded[k : k + n + 8]
    left = ends - np.arange(n)
    seven = np.minimum(left, 7)
    # bytes past a segment's end do not count; of two that agree so far the shorter is first
    key = (words[:n] >> np.uint64(8)) >> (np.uint64(8) * (7 - seven).astype(np.uint64)) << (np.uint64(8) * (7 - seven).astype(np.uint64))
    key = (key << np.uint64(3)) | seven.astype(np.uint64)
    sa = np.argsort(key, kind="stable")
    k = key[sa]
    fresh = np.ones(n, bool)
    fresh[1:] = k[1:] != k[:-1]
    rank = np.empty(n, np.int64)
    rank[sa] = np.maximum.accumulate(np.where(fresh, np.arange(n), 0))
    depth = 7
    while True:
        single = fresh & np.append(fresh[1:], True)
        open_ = np.flatnonzero(~single)
        if not len(open_):
            break
        sub = sa[open_]
        follow = np.where(left[sub] > depth, rank[np.minimum(sub + depth, n - 1)] + 1, 0)
        if depth > int(left[sub].max()):
            break
        two = rank[sub] * (n + 1) + follow
        order = np.argsort(two, kind="stable")
        sub, two = sub[order], two[order]
        sa[open_] = sub
        new = np.ones(len(sub), bool)
        new[1:] = two[1:] != two[:-1]
        fresh[open_] = new
        rank[sub] = np.maximum.accumulate(np.where(new, open_, 0))
        depth *= 2
    # equal suffixes in order of place: the stable sorts have kept it
    return sa, words


def common_prefixes(sa: np.ndarray, words: np.ndarray, begins: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Common prefix of each suffix with the one before it in ``sa``, found in text order: the
    next place's prefix is shorter by one at most. All segments advance side by side."""
    n = len(sa)
    before = np.full(n, -1, np.int64)
    before[sa[1:]] = sa[:-1]
    ends = np.repeat(begins + sizes, sizes)
    out = np.zeros(n, np.int64)
    order = np.argsort(-sizes, kind="stable")
    begins, sizes = begins[order], sizes[order]
    h = np.zeros(len(begins), np.int64)
    for t in range(int(sizes[0]) if len(sizes) else 0):
        m = int(np.searchsorted(-sizes, -t, "left"))
        p = begins[:m] + t
        q = before[p]
        cap = np.minimum(ends[p] - p, np.where(q >= 0, ends[q] - q, 0))
        h = np.maximum(h[:m] - 1, 0)
        run = np.flatnonzero(h < cap)
        while len(run):
            x = words[p[run] + h[run]] ^ words[q[run] + h[run]]
            same = x == 0
            # equal bytes that lead the first word that differs
            d = x[~same]
            lead = np.zeros(len(d), np.int64)
            for k in range(1, 8):
                lead += d < np.uint64(1 << (64 - 8 * k))
            h[run[~same]] += lead
            h[run[same]] += 8
            run = run[same]
            run = run[h[run] < cap[run]]
        h = np.minimum(h, cap)
        out[p] = h
    lcp = out[sa]
    return lcp


def repeated_starts(segments: list[bytes], length: int = LENGTH) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(segment, start, class) of every string of ``length`` bytes in ``segments``, in suffix
    order; equal strings have the same class."""
    sizes = np.array([len(s) for s in segments], np.int64)
    begins = np.cumsum(sizes) - sizes
    text = np.frombuffer(b"".join(segments), np.uint8)
    ends = np.repeat(begins + sizes, sizes)
    sa, words = suffix_array(text, ends)
    lcp = common_prefixes(sa, words, begins, sizes)
    whole = ends[sa] - sa >= length
    # prefixes between two whole strings: the least on the way, which is that of the next one
    group = np.cumsum(lcp < length)
    at = sa[whole]
    seg = np.searchsorted(begins + sizes, at, "right")
    return seg, at - begins[seg], group[whole]


def _runs(doc: np.ndarray, start: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(doc, from, to) of the bytes of strings, those one byte apart as one."""
    order = np.lexsort((start, doc))
    doc, start = doc[order], start[order]
    new = np.ones(len(doc), bool)
    new[1:] = (doc[1:] != doc[:-1]) | (start[1:] != start[:-1] + 1)
    first = np.flatnonzero(new)
    last = np.append(first[1:] - 1, len(doc) - 1) if len(first) else first
    return doc[first], start[first], start[last] + length


def repeated_intervals(src: DataFrame, length: int = LENGTH) -> tuple[DataFrame, DataFrame]:
    """(intervals, touched) of written rows (id, t), ids being unique row numbers: (id, lo, hi) byte
    ranges made of repeated strings, unmerged, and the (id, t) of rows that can have any.

    Whether an anchor or its surroundings occur again is counted first, combined before it is
    shuffled; the join that hands the counts to the anchors is written at once, so that a very
    common anchor is split over tasks."""

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            raw, off = text_buffer(b.column(1))
            ids = b.column(0).to_numpy()
            for lo, hi in byte_slices(off):
                a = anchors(raw[off[lo] : off[hi]], off[lo : hi + 1] - off[lo], length)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(a["gram"].view(np.int64)), pa.array(a["around"].view(np.int64)), pa.array(ids[lo:hi][a["row"]]),
                     pa.array(a["at"].astype(np.int32)), pa.array(a["lo"].astype(np.int32)), pa.array(a["n"].astype(np.int32))],
                    ["gram", "around", "id", "at", "lo", "n"],
                )

    found = written(src.mapInArrow(tidy(scan), "gram long, around long, id long, at int, lo int, n int"), "anchors")
    around = written(found.groupBy("gram", "around").agg(F.count("*").alias("copies")), "surroundings")
    per_gram = around.groupBy("gram").agg(F.sum("copies").alias("_c"), F.count("*").alias("kinds"), F.min("copies").alias("least")).where("_c > 1")
    counted = written(around.join(per_gram.select("gram", "kinds", "least"), "gram"), "counted")
    dup = written(found.join(counted, ["gram", "around"]), "anchors-again")
    # surroundings that occur again as a whole are settled
    settled_ = dup.where("copies > 1").select("id", "lo", (F.col("lo") + F.col("n") - 1 + length).alias("hi"))
    # of the others, and one of each kind that is settled, those meet whose anchor has several kinds
    mixed = dup.where("kinds > 1 and least = 1").withColumn("one", F.struct("id", "at", "lo", "n"))
    lone = mixed.where("copies = 1").select("gram", "around", "kinds", F.lit(True).alias("lone"), "one.*")
    known = mixed.where("copies > 1").groupBy("gram", "around", "kinds").agg(F.min("one").alias("one")).select("gram", "around", "kinds", F.lit(False).alias("lone"), "one.*")
    meet = written(lone.unionByName(known), "meeting")
    touched = dup.select("id").distinct()
    texts = written(src.join(touched, "id", "left_semi"), "touched")
    total = meet.agg(F.sum(F.col("n") + length - 1)).first()[0] or 0
    n_shards = max(1, -(-int(total) // SHARD_BYTES))
    wants = meet.groupBy("id").agg(F.collect_list(F.struct("gram", "around", "kinds", "lone", "at", "lo", "n")).alias("w"))

    def extract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["gram", "around", "kinds", "lone", "at", "lo", "n"]
        kinds = [pa.int64()] * 3 + [pa.bool_()] + [pa.int32()] * 3
        for b in batches:
            raw, off = text_buffer(b.column(1))
            for i, ws in enumerate(b.column(2).to_pylist()):
                doc = raw[off[i] : off[i + 1]]
                id_ = b.column(0)[i].as_py()
                cols = [pa.array([w[k] for w in ws], t) for k, t in zip(names, kinds)]
                segs = [doc[w["lo"] : w["lo"] + w["n"] - 1 + length].tobytes() for w in ws]
                yield pa.RecordBatch.from_arrays([*cols, pa.array([id_] * len(ws)), pa.array(segs, pa.binary())], [*names, "id", "seg"])

    segments = texts.join(wants, "id").select("id", "t", "w").mapInArrow(
        tidy(extract), "gram long, around long, kinds long, lone boolean, at int, lo int, n int, id long, seg binary"
    )
    hot = F.col("kinds") > HOT
    dealt = segments.withColumn("shard", F.when(hot, F.col("gram")).otherwise(F.pmod("gram", F.lit(n_shards)))).withColumn(
        "sub", F.when(hot, 1 + F.pmod("around", F.ceil(F.col("kinds") / HOT))).otherwise(0)
    )
    out_schema = pa.schema(
        [("id", pa.int64()), ("lo", pa.int64()), ("hi", pa.int64()), ("gram", pa.int64()), ("bucket", pa.int64()), ("print", pa.binary()), ("ids", pa.binary()), ("los", pa.binary())]
    )
    out_ddl = "id long, lo long, hi long, gram long, bucket long, print binary, ids binary, los binary"

    def order(table: pa.Table) -> pa.Table:
        segs = table.column("seg").to_pylist()
        seg, start, cls = repeated_starts(segs, length)
        _, back, size = np.unique(cls, return_inverse=True, return_counts=True)
        lone = table.column("lone").to_numpy()
        ids, lo0 = table.column("id").to_numpy(), table.column("lo").to_numpy().astype(np.int64)
        hit = (size[back] > 1) & lone[seg]
        d, lo, hi = _runs(ids[seg[hit]], lo0[seg[hit]] + start[hit], length)
        rows = {"id": d, "lo": lo, "hi": hi, "gram": np.zeros(len(d), np.int64), "bucket": np.zeros(len(d), np.int64)}
        blank = [None] * len(d)
        cols = {k: list(v) for k, v in rows.items()} | {"print": list(blank), "ids": list(blank), "los": list(blank)}
        if table.column("sub")[0].as_py():
            # one of each class goes to the other shards of this anchor, with what it stands for
            first = np.unique(cls, return_index=True)[1]
            sizes = np.array([len(s) for s in segs], np.int64)
            begins = np.cumsum(sizes) - sizes
            roll = RollingHash(np.frombuffer(b"".join(segs), np.uint8))
            at = begins[seg[first]] + start[first]
            prints = roll.of(at, at + length)
            ask = (size[back[first]] == 1) & lone[seg[first]]
            who = np.where(ask, ids[seg[first]], -1)
            los = lo0[seg[first]] + start[first]
            place = table.column("at").to_numpy()[seg[first]] - los
            spread = np.uint64(max(1, table.column("kinds")[0].as_py() >> 17))
            bucket = (place // 16) * (1 << 32) + (prints % spread).astype(np.int64)
            for k in np.unique(bucket):
                m = np.flatnonzero(bucket == k)
                m = m[np.argsort(prints[m])]
                for name, v in (("id", None), ("lo", None), ("hi", None), ("gram", table.column("gram")[0].as_py()), ("bucket", int(k)),
                                ("print", prints[m].tobytes()), ("ids", who[m].astype("<i8").tobytes()), ("los", los[m].astype("<i8").tobytes())):
                    cols[name].append(v)
        return pa.table({f.name: pa.array(cols[f.name], f.type) for f in out_schema}, out_schema)

    local = written(dealt.groupBy("shard", "sub").applyInArrow(tidy(order), out_ddl), "shard-results")

    def merge(table: pa.Table) -> pa.Table:
        lists = [np.frombuffer(x, "<u8") for x in table.column("print").to_pylist()]
        every, times = np.unique(np.concatenate(lists), return_counts=True)
        shared = every[times > 1]
        d, lo = [], []
        for prints, ids, los in zip(lists, table.column("ids").to_pylist(), table.column("los").to_pylist()):
            at = np.searchsorted(shared, prints)
            hit = np.zeros(len(prints), bool)
            if len(shared):
                hit = shared[np.minimum(at, len(shared) - 1)] == prints
            ids, los = np.frombuffer(ids, "<i8"), np.frombuffer(los, "<i8")
            hit &= ids >= 0
            d.append(ids[hit])
            lo.append(los[hit])
        d, lo, hi = _runs(np.concatenate(d), np.concatenate(lo), length)
        return pa.table({"id": pa.array(d, pa.int64()), "lo": pa.array(lo, pa.int64()), "hi": pa.array(hi, pa.int64())})

    across = local.where(F.col("print").isNotNull()).groupBy("gram", "bucket").applyInArrow(tidy(merge), "id long, lo long, hi long")
    inside = local.where(F.col("id").isNotNull()).select("id", "lo", "hi")
    return settled_.select("id", F.col("lo").cast("long").alias("lo"), F.col("hi").cast("long").alias("hi")).unionByName(inside).unionByName(across), texts


def merged_spans(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Ranges that overlap or touch, joined."""
    out: list[list[int]] = []
    for lo, hi in sorted(spans):
        if out and lo <= out[-1][1]:
            out[-1][1] = max(out[-1][1], hi)
        else:
            out.append([lo, hi])
    return [(a, b) for a, b in out]


def remove_repeats(df: DataFrame, text: str, key: str, length: int = LENGTH) -> DataFrame:
    """(id, n_bytes, spans, kept, kept_sha256) for every row of ``df``: the key, the text's UTF-8
    length, the removed byte ranges, the bytes that stay (null where nothing is removed and they
    are the text's own) and the digest of the bytes that stay.

    Null and empty texts have no bytes. Texts shorter than ``length`` stay whole. Rows are texts of
    their own, also where their keys are null or repeat: a text given twice repeats itself. Bytes
    that stay need not be valid UTF-8, as ranges are cut without regard to characters. Other
    columns are ignored; an empty table gives no rows.
    """
    src = numbered(df.select(F.col(key).alias("key"), F.col(text).alias("t")), "id", "texts", keep=True)
    utf8 = F.coalesce(F.col("t"), F.lit("")).cast("binary")
    base = src.select("key", F.col("id").alias("_id"), F.length(utf8).cast("long").alias("n_bytes"), F.sha2(utf8, 256).alias("_own"))
    intervals, texts = repeated_intervals(src.select("id", "t"), length)
    per_doc = intervals.groupBy("id").agg(F.collect_list(F.struct("lo", "hi")).alias("s"))
    kind = pa.list_(pa.struct([("lo", pa.int64()), ("hi", pa.int64())]))

    def cut_out(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            raw, off = text_buffer(b.column(1))
            spans, kept = [], []
            for i, s in enumerate(b.column(2).to_pylist()):
                m = merged_spans([(x["lo"], x["hi"]) for x in s])
                doc, at, parts = raw[off[i] : off[i + 1]], 0, []
                for lo, hi in m:
                    parts.append(doc[at:lo].tobytes())
                    at = hi
                kept.append(b"".join([*parts, doc[at:].tobytes()]))
                spans.append([{"lo": lo, "hi": hi} for lo, hi in m])
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(spans, kind), pa.array(kept, pa.binary())], ["id", "spans", "kept"])

    changed = texts.join(per_doc, "id").select("id", "t", "s").mapInArrow(tidy(cut_out), "id long, spans array<struct<lo:long,hi:long>>, kept binary")
    changed = written(changed.withColumn("_sha", F.sha2("kept", 256)), "cut", keep=True)
    return base.join(changed, F.col("_id") == F.col("id"), "left").select(
        F.col("key").alias("id"), "n_bytes", F.coalesce("spans", F.array().cast(changed.schema["spans"].dataType)).alias("spans"), "kept", F.coalesce("_sha", "_own").alias("kept_sha256")
    )


@settled
def op5_suffix_array_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What is removed from every document; see ``remove_repeats``."""
    out = remove_repeats(read_table(spark, sf_dir, "documents"), "text", "doc_id")
    removed = F.aggregate("spans", F.lit(0).cast("long"), lambda a, s: a + s["hi"] - s["lo"])
    return out.select(F.col("id").alias("doc_id"), "n_bytes", removed.alias("n_removed"), F.size("spans").cast("long").alias("n_spans"), "kept_sha256")
