"""Near-duplicate documents by an inverted join over signature coordinates (operator 2)."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import byte_slices, mix64, numbered, read_table, salted_powers, segment_hash, settled, text_buffer, tidy, word_bounds, written
from .components import connected_components
from .positions import Positions, write_positions

#: Fixed values of the contract: words in a shingle, least similarity in percent.
SHINGLE_WORDS = 4
PERCENT = 80
#: Signature length and the number of equal coordinates that makes a candidate. At a
#: similarity of exactly 0.8 a pair has 51.2 equal coordinates on average and fewer than 36
#: with a probability of 5e-6; from 0.85 on it is below 1e-8.
COORDINATES = 64
MATCHES = 36
#: Shingles of the documents that a task compares at a time, on either side.
BLOCK_SHINGLES = 1 << 20

_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_STEP = np.uint64(0xD6E8FEB86659FD93)


def shingle_sets(raw: np.ndarray, offsets: np.ndarray, words: int) -> tuple[np.ndarray, np.ndarray]:
    """(shingles, counts): each row's distinct shingle hashes in ascending order, joined.

    A text with fewer words than a shingle is one shingle; one without words has none."""
    n = len(offsets) - 1
    low = _LOWER[raw]
    starts, ends, rows = word_bounds(low, offsets)
    h = segment_hash(low, starts, ends)
    per_row = np.bincount(rows, minlength=n)
    first = np.cumsum(per_row) - per_row
    parts, owner = [], []
    m = len(h) - words + 1
    if m > 0:
        s = np.zeros(m, np.uint64)
        for k in range(words):
            s = s * _STEP + h[k : k + m]
        whole = np.flatnonzero(rows[:m] == rows[words - 1 :])
        parts.append(mix64(s[whole]))
        owner.append(rows[whole])
    short = np.flatnonzero((per_row > 0) & (per_row < words))
    if len(short):
        s = per_row[short].astype(np.uint64)
        for k in range(words - 1):
            more = per_row[short] > k
            s[more] = s[more] * _STEP + h[first[short][more] + k]
        parts.append(mix64(s))
        owner.append(short)
    if not parts:
        return np.zeros(0, np.uint64), np.zeros(n, np.int64)
    values, owners = np.concatenate(parts), np.concatenate(owner)
    order = np.lexsort((values, owners))
    values, owners = values[order], owners[order]
    fresh = np.ones(len(values), bool)
    fresh[1:] = (values[1:] != values[:-1]) | (owners[1:] != owners[:-1])
    return values[fresh], np.bincount(owners[fresh], minlength=n)


_FACTORS = salted_powers(COORDINATES, 0xC0FFEE)
_FLIPS = salted_powers(COORDINATES, 0xFACADE)


def signatures(shingles: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """(rows with shingles, COORDINATES) minima, 32 bits each."""
    begin = (np.cumsum(counts) - counts)[counts > 0]
    out = np.empty((len(begin), COORDINATES), np.uint32)
    for k in range(COORDINATES if len(begin) else 0):
        out[:, k] = np.minimum.reduceat((shingles ^ _FLIPS[k]) * _FACTORS[k], begin) >> np.uint64(32)
    return out


def signature_rows(rows: DataFrame, words: int) -> DataFrame:
    """(row, id, n, set_a, set_b, sig) of (row, id, t) rows: set size, a 128-bit digest of the set, the
    signature."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            raw, off = text_buffer(b.column(2))
            for lo, hi in byte_slices(off):
                sh, n = shingle_sets(raw[off[lo] : off[hi]], off[lo : hi + 1] - off[lo], words)
                sig = np.zeros((len(n), COORDINATES), np.uint32)
                sig[n > 0] = signatures(sh, n)
                one, two = np.zeros(len(n), np.uint64), np.zeros(len(n), np.uint64)
                if len(sh):
                    begin = (np.cumsum(n) - n)[n > 0]
                    one[n > 0] = np.add.reduceat(sh, begin)
                    two[n > 0] = np.add.reduceat(mix64(sh ^ np.uint64(0xA5A5A5A5A5A5A5A5)), begin)
                lists = pa.ListArray.from_arrays(pa.array(np.arange(len(n) + 1, dtype=np.int32) * COORDINATES), pa.array(sig.ravel().astype(np.int64)))
                own = [b.column(k).slice(lo, hi - lo) for k in (0, 1)]
                yield pa.RecordBatch.from_arrays(
                    [*own, pa.array(n.astype(np.int64)), pa.array(one.view(np.int64)), pa.array(two.view(np.int64)), lists], ["row", "id", "n", "set_a", "set_b", "sig"]
                )

    return rows.mapInArrow(tidy(run), "row long, id long, n long, set_a long, set_b long, sig array<long>")


def shingle_rows(rows: DataFrame, words: int, folder: str) -> DataFrame:
    """(id, shingles) of the (row, id, t) rows that have a value in a folder of positions: their row
    numbers and whole sets, for confirming links. Rows are picked where they lie, without a join."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        asked = Positions(folder)
        for b in batches:
            mask = asked.of(b.column(0).to_numpy()) >= 0
            b = b.filter(pa.array(mask))
            raw, off = text_buffer(b.column(2))
            for lo, hi in byte_slices(off):
                sh, n = shingle_sets(raw[off[lo] : off[hi]], off[lo : hi + 1] - off[lo], words)
                ends = np.concatenate([[0], np.cumsum(n)]).astype(np.int32)
                yield pa.RecordBatch.from_arrays([b.column(0).slice(lo, hi - lo), pa.ListArray.from_arrays(pa.array(ends), pa.array(sh.view(np.int64)))], ["id", "shingles"])

    return rows.mapInArrow(tidy(run), "id long, shingles array<long>")


def prefix_postings(reps: DataFrame, matches: int = MATCHES) -> DataFrame:
    """(key, id): the postings that a pair with enough equal coordinates must share.

    A document is the set of its coordinate-value pairs, ordered from the rarest to the most
    frequent. Two such sets of k pairs with t in common share one of each other's first
    k - t + 1; so only those are posted. Values that very many documents hold come last
    in the order and are hardly ever posted. Pairs that just one document holds fill the
    prefix without a posting.
    """
    pairs = reps.select("id", F.posexplode("sig").alias("_i", "_v")).select(
        (F.shiftleft(F.col("_i").cast("long"), 32) + F.col("_v")).alias("key"), "id"
    )
    shared = pairs.groupBy("key").agg(F.count("*").alias("freq")).where("freq > 1")
    # at most COORDINATES entries a document
    mine = pairs.join(shared, "key").groupBy("id").agg(F.sort_array(F.collect_list(F.struct("freq", "key"))).alias("_l"))
    room = F.lit(COORDINATES - matches + 1) - (F.lit(COORDINATES) - F.size("_l"))
    return (
        mine.withColumn("_room", room)
        .where("_room > 0")
        .select("id", F.explode(F.slice("_l", F.lit(1), F.col("_room"))).alias("_p"))
        .select("_p.key", "id")
    )


def _confirmed(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b) whose whole sets are similar enough."""
    one = sets.select(F.col("id").alias("a"), F.col("shingles").alias("_sa"))
    two = sets.select(F.col("id").alias("b"), F.col("shingles").alias("_sb"))
    na, nb = F.size("_sa").cast("long"), F.size("_sb").cast("long")
    # sizes alone rule out many pairs before sets are compared
    joined = pairs.join(one, "a").join(two, "b").where((100 * F.least(na, nb)) >= percent * F.greatest(na, nb))
    common = F.size(F.array_intersect("_sa", "_sb")).cast("long")
    return joined.withColumn("_c", common).where((100 * F.col("_c")) >= percent * (na + nb - F.col("_c"))).select("a", "b")


def _links_between(base: tuple, ask: tuple, matches: int, percent: int) -> tuple[np.ndarray, np.ndarray]:
    """Links that join classes, out of the pairs of an asking and a base document.

    The base documents are posted under each coordinate's values. For an asking document, the
    lists of its values are merged from the shortest to the longest: a partner with enough equal
    coordinates is on one of the first COORDINATES - matches + 1, so those alone bring partners,
    and the longer lists are only asked about the partners that can still get there. Partners
    of the asking document's own class are skipped, also when a link found here has just made them
    so. What has enough equal coordinates is confirmed on whole sets, the most similar first."""
    b_id, b_cls, b_sig, b_sets, b_n = base
    a_id, a_cls, a_sig, a_sets, a_n = ask
    b_begin, a_begin = np.cumsum(b_n) - b_n, np.cumsum(a_n) - a_n
    _, code = np.unique(np.concatenate([b_cls, a_cls]), return_inverse=True)
    label = np.arange(code.max() + 1 if len(code) else 0)  # class of each first class
    b_code, a_code = code[: len(b_cls)], code[len(b_cls) :]
    posted = np.argsort(b_sig, axis=0, kind="stable")
    values = np.take_along_axis(b_sig, posted, 0)
    lo, hi = np.empty((2, len(a_id), COORDINATES), np.int64)
    for k in range(COORDINATES):
        lo[:, k] = np.searchsorted(values[:, k], a_sig[:, k], "left")
        hi[:, k] = np.searchsorted(values[:, k], a_sig[:, k], "right")
    prefix = COORDINATES - matches + 1
    found_a, found_b = [], []
    for i in range(len(a_id)):
        order = np.argsort(hi[i] - lo[i], kind="stable")
        lists = [posted[lo[i, k] : hi[i, k], k] for k in order[:prefix].tolist() if hi[i, k] > lo[i, k]]
        if not lists:
            continue
        partner, equal = np.unique(np.concatenate(lists), return_counts=True)
        small, large = np.minimum(b_n[partner], a_n[i]), np.maximum(b_n[partner], a_n[i])
        good = (label[b_code[partner]] != label[a_code[i]]) & (100 * small >= percent * large)
        partner, equal = partner[good], equal[good]
        for j, k in enumerate(order[prefix:].tolist()):
            can = equal + (matches - 1 - j) >= matches  # coordinates still to come
            partner, equal = partner[can], equal[can]
            if not len(partner):
                break
            equal = equal + (b_sig[partner, k] == a_sig[i, k])
        enough = equal >= matches
        partner, equal = partner[enough], equal[enough]
        partner = partner[np.argsort(-equal, kind="stable")]
        mine = a_sets[a_begin[i] : a_begin[i] + a_n[i]]
        for first, last in ((0, 16), (16, len(partner))):
            part = partner[first:last]
            part = part[label[b_code[part]] != label[a_code[i]]]
            if not len(part):
                continue
            n = b_n[part]
            start = np.cumsum(n) - n
            theirs = b_sets[np.arange(int(n.sum())) + np.repeat(b_begin[part] - start, n)]
            at = np.searchsorted(mine, theirs)
            same = mine[np.minimum(at, len(mine) - 1)] == theirs
            common = np.add.reduceat(same.astype(np.int64), start)
            for j in part[100 * common >= percent * (n + a_n[i] - common)].tolist():
                x, y = label[b_code[j]], label[a_code[i]]
                if x != y:
                    found_a.append(int(a_id[i]))
                    found_b.append(int(b_id[j]))
                    label[label == max(x, y)] = min(x, y)
    return np.array(found_a, np.int64), np.array(found_b, np.int64)


def _family_links(lists: DataFrame, sets: DataFrame, sigs: DataFrame, matches: int, percent: int) -> DataFrame:
    """Links (a, b) between different classes out of posting lists (key, id, class).

    Lists inside one class are skipped. Documents that the other lists connect are a family; each
    is compared once, however many lists it is on. The largest class of a family asks nothing:
    its documents, like all, are spread over base blocks by a hash; the rest is spread over
    asking blocks, and every asking block meets every base block of its family. A block holds
    about BLOCK_SHINGLES shingles. Tasks return links that join classes, never candidates.
    """
    mixed = lists.groupBy("key").agg(F.min("class").alias("_lo"), F.max("class").alias("_hi")).where("_lo < _hi")
    on_mixed = lists.join(mixed.select("key", F.col("_lo").alias("hub")), "key")
    # families join classes, of which there are fewer than documents
    families = connected_components(on_mixed.where("class <> hub").select(F.col("class").alias("a"), F.col("hub").alias("b")))
    families = families.select(F.col("node").alias("class"), F.col("component").alias("family"))
    members = on_mixed.select("id", "class").distinct().join(families, "class").join(sets, "id").join(sigs, "id")
    members = written(members, "families")
    weight = F.size("shingles").cast("long")
    per_class = members.groupBy("family", "class").agg(F.sum(weight).alias("_w"))
    per_family = per_class.groupBy("family").agg(F.sum("_w").alias("_all"), F.max(F.struct("_w", "class")).alias("_top"))
    blocks = per_family.select(
        "family",
        F.col("_top.class").alias("_main"),
        F.ceil(F.col("_all") / BLOCK_SHINGLES).cast("int").alias("_bases"),
        F.greatest(F.lit(1), F.ceil((F.col("_all") - F.col("_top._w")) / BLOCK_SHINGLES).cast("int")).alias("_askers"),
    )
    # a row for each family
    rows = members.join(blocks, "family")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    mine = lambda n: F.pmod(F.xxhash64("id"), F.col(n)).cast("int")
    cols = ["family", "id", "class", "sig", "shingles"]
    base = rows.select(*cols, mine("_bases").alias("base"), F.lit(False).alias("asks"), every("_askers").alias("asker"))
    ask = rows.where(F.col("class") != F.col("_main")).select(*cols, every("_bases").alias("base"), F.lit(True).alias("asks"), mine("_askers").alias("asker"))

    def compare(table: pa.Table) -> pa.Table:
        sides = []
        for t in (table.filter(pa.compute.invert(table.column("asks"))), table.filter(table.column("asks"))):
            shingles = t.column("shingles").combine_chunks()
            n = np.array(shingles.value_lengths(), np.int64)
            sig = t.column("sig").combine_chunks().flatten().to_numpy().astype(np.uint32).reshape(len(t), COORDINATES)
            sides.append((t.column("id").to_numpy(), t.column("class").to_numpy(), sig, shingles.flatten().to_numpy().view(np.uint64), n))
        a, b = _links_between(*sides, matches, percent)
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

    # dealt anew by all three: a partitioning by family alone would do for the groups, and hold a family in one task
    dealt = base.unionByName(ask.select(base.columns)).repartition("family", "base", "asker")
    return dealt.groupBy("family", "base", "asker").applyInArrow(tidy(compare), "a long, b long")


def near_duplicate_classes(
    df: DataFrame, text: str, key: str, words: int = SHINGLE_WORDS, percent: int = PERCENT, matches: int = MATCHES, row: str | None = None
) -> DataFrame:
    """(id, n_shingles, component_id, first) and ``row``, if a column is named, for each row:
    classes of documents linked by similar shingle sets.

    ``component_id`` is the smallest key that links reach; every link counts, chains too. ``first``
    holds for one row of each class, one with that key. ``row`` is a column of row numbers from
    ``numbered``, in a table that is written already; else the texts are written with numbers first.

    1. Documents with equal sets are one class at once; one of each set goes on.
    2. Signatures' coordinate-value pairs are posted by prefix (``prefix_postings``).
    3. Each document is compared with the first and the last of its lists' documents: links
       that hold, on whole sets, make classes. This takes a group of copies of any size
       with a number of comparisons in proportion to it.
    4. Documents on lists that still hold different classes are compared in blocks, by merging
       the lists of a block with skips (``_links_between``); pairs of one class are skipped.

    A link is missed only if its signatures differ more than MATCHES allows. Null, empty and
    blank texts have no shingles and stand alone. Rows with one key are documents of their own,
    linked like others. Rows with a null key stand alone: they link with nothing, their
    ``component_id`` is null. Other columns are ignored; an empty table gives no rows.
    """
    texts = df.select(*([F.col(row).alias("row")] if row else []), F.col(key).cast("long").alias("id"), F.col(text).alias("t"))
    texts = (texts if row else numbered(texts, "row", "texts")).select("row", "id", "t")
    rows = written(signature_rows(texts, words), "signatures", keep=True)
    with_set = rows.where("n > 0 and id is not null")
    heads = written(with_set.groupBy("set_a", "set_b", "n").agg(F.min("row").alias("rep"), F.min("id").alias("least")), "set-heads", keep=True)
    reps = rows.join(heads.select(F.col("rep").alias("row")), "row", "left_semi").select(F.col("row").alias("id"), "sig")
    posts = written(prefix_postings(reps, matches), "postings")
    ends = posts.groupBy("key").agg(F.min("id").alias("lo"), F.max("id").alias("hi")).where("lo < hi")
    listed = written(posts.join(ends, "key"), "posting-lists")
    hubs = listed.groupBy("id").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi"))
    asked = write_positions(hubs.select("id", F.lit(1).alias("v")), "asked")
    sets = written(shingle_rows(texts, words, asked), "shingles")
    name = written(hubs.select("id", F.explode(F.array("lo", "hi")).alias("_h")).where("id <> _h"), "hubs")
    near = name.select(F.least("id", "_h").alias("a"), F.greatest("id", "_h").alias("b")).distinct()
    first = written(_confirmed(near, sets, percent), "links")
    # a document takes the name of its first linked hub, then of that one's; documents of one
    # name are connected, and not all that are connected need to have one name yet
    linked = first.select(F.inline(F.array(F.struct(F.col("a").alias("id"), F.col("b").alias("_h")), F.struct(F.col("b").alias("id"), F.col("a").alias("_h")))))
    name = written(name.join(linked, ["id", "_h"], "left_semi").groupBy("id").agg(F.min("_h").alias("_h")), "names")
    up = name.select(F.col("id").alias("_h"), F.col("_h").alias("_up"))
    classes = name.join(up, "_h", "left").select("id", F.coalesce("_up", "_h").alias("class"))
    labelled = written(listed.select("key", "id").join(classes, "id", "left").select("key", "id", F.coalesce("class", "id").alias("class")), "labelled")
    second = written(_family_links(labelled, sets, reps, matches, percent), "links")
    joined = connected_components(first.unionByName(second)).select(F.col("node").alias("rep"), "component")
    # a class is named after its smallest key, and its first row is the first one with that key
    top = written(heads.join(joined, "rep", "left").withColumn("_c", F.coalesce("component", "rep")), "set-classes", keep=True)
    names = top.groupBy("_c").agg(F.min(F.struct("least", "rep")).alias("_m")).select(F.col("_c").alias("_k"), F.col("_m.least").alias("_least"), F.col("_m.rep").alias("_owner"))
    top = top.join(names, F.col("_c") == F.col("_k")).select(
        F.col("set_a").alias("_a"), F.col("set_b").alias("_b"), F.col("n").alias("_n"), "_least", (F.col("rep") == F.col("_owner")).alias("_own")
    )
    same_set = (F.col("set_a") == F.col("_a")) & (F.col("set_b") == F.col("_b")) & (F.col("n") == F.col("_n"))
    out = rows.select("row", "id", "n", "set_a", "set_b").withColumn("_has", F.col("id").isNotNull() & (F.col("n") > 0))
    out = out.join(top, F.col("_has") & same_set, "left")
    # of the rows of the set that holds the smallest key, the first one with it
    lead = with_set.select("row", "id", "n", "set_a", "set_b").join(top.where("_own"), same_set & (F.col("id") == F.col("_least")))
    lead = lead.groupBy("_a", "_b", "_n").agg(F.min("row").alias("_lead")).select("_lead")
    return out.join(lead, F.col("row") == F.col("_lead"), "left").select(
        "id", F.col("n").alias("n_shingles"), F.when(F.col("_has"), F.col("_least")).otherwise(F.col("id")).alias("component_id"),
        (~F.col("_has") | F.col("_lead").isNotNull()).alias("first"), *["row"] * bool(row),
    )


@settled
def op2_minhash_classes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Class of every document; see ``near_duplicate_classes``."""
    docs = read_table(spark, sf_dir, "documents")
    out = near_duplicate_classes(docs, "text", "doc_id")
    kept = F.col("id").eqNullSafe(F.col("component_id"))
    return out.select(F.col("id").alias("doc_id"), "n_shingles", "component_id", kept.alias("kept"))
