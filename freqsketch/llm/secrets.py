"""Secret scans with corpus-wide ownership frequency (operator 7).

Pattern matches are hashed and counted by distinct repositories and owners over the whole
corpus: a value that several owners share, or that stands in many repositories, is a copied
example; one that stays with few looks live.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import numbered, read_table, settled, tidy, written

#: The base kinds in their order, their patterns and least lengths.
KINDS = ("assign", "access", "hex")
PATTERNS = {
    "assign": r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""",
    "access": r"AKIA[A-Z0-9]+",
    "hex": r"[0-9a-f]+",
}
LEAST = {"assign": 6, "access": 20, "hex": 24}

#: The kind that this method adds: long mixed strings which no base span touches and which
#: stay with one owner.
LIVE = "live"
LIVE_PATTERN = r"[A-Za-z0-9+/_-]{24,}"
LIVE_BITS = 3.5
#: A value found with so many distinct owners or more, or in so many distinct repositories or more
#: whoever owns them, is a copied example.
EXAMPLE_OWNERS = 3
EXAMPLE_REPOSITORIES = 4

_ASSIGN = re.compile(PATTERNS["assign"], re.I | re.A)
_ACCESS = re.compile(r"AKIA[A-Z0-9]{16,}")
#: Maximal runs of 24 or more are the runs that reach 24, so the bound can be in the pattern.
_HEX = re.compile(r"[0-9a-f]{24,}")
_LIVE = re.compile(LIVE_PATTERN)
#: A text without any of these holds no span of any kind (linear-time scan in Arrow).
_ANY = (
    r"(?i:password|passwd|secret|token|api_?key)[\"']?\x20*[:=]"
    r"|AKIA[A-Z0-9]{16}|[0-9a-f]{24}|[A-Za-z0-9+/_\-]{24}"
)
_SPAN = "struct<kind:string,start:long,end:long,value:string>"


def _entropy(s: str) -> float:
    n = len(s)
    return -sum(c / n * math.log2(c / n) for c in Counter(s).values())


def find_spans(text: str) -> list[tuple[str, int, int, str]]:
    """Candidates (kind, start, end, secret value) in code points, by start, then kind."""
    found = []
    for m in _ASSIGN.finditer(text):
        if len(m[2]) >= LEAST["assign"]:
            found.append(("assign", m.start(), m.end(), m[2]))
    found += [("access", m.start(), m.end(), m[0]) for m in _ACCESS.finditer(text)]
    found += [("hex", m.start(), m.end(), m[0]) for m in _HEX.finditer(text)]
    taken = sorted((s, e) for _, s, e, _ in found)
    at = 0
    reach = 0
    for m in _LIVE.finditer(text):
        s, e = m.span()
        while at < len(taken) and taken[at][0] < e:
            reach = max(reach, taken[at][1])
            at += 1
        v = m[0]
        if reach > s or not (any(c.isdigit() for c in v) and any(c.isupper() for c in v) and any(c.islower() for c in v)):
            continue
        if _entropy(v) >= LIVE_BITS:
            found.append((LIVE, s, e, v))
    rank = {k: i for i, k in enumerate((*KINDS, LIVE))}
    return sorted(found, key=lambda x: (x[1], rank[x[0]], x[2]))


def with_candidates(df: DataFrame, text: str, keep: list[str]) -> DataFrame:
    """Columns of ``keep`` and ``spans``: an array of (kind, start, end, value)."""
    picked = df.select(*keep, F.col(text).alias("_text"))
    fields = [f for f in picked.schema.fields if f.name != "_text"]
    schema = ", ".join([f"`{f.name}` {f.dataType.simpleString()}" for f in fields] + [f"spans array<{_SPAN}>"])
    kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64()), ("value", pa.string())]))

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            text_col = b.column(b.schema.get_field_index("_text"))
            hit = pc.fill_null(pc.match_substring_regex(text_col, _ANY), False)
            spans: list = [[]] * len(b)
            for i in pc.indices_nonzero(hit).to_pylist():
                found = find_spans(text_col[i].as_py())
                spans[i] = [{"kind": k, "start": s, "end": e, "value": v} for k, s, e, v in found]
            yield pa.RecordBatch.from_arrays(
                [b.column(b.schema.get_field_index(f.name)) for f in fields] + [pa.array(spans, kind)],
                [f.name for f in fields] + ["spans"],
            )

    return picked.mapInArrow(tidy(scan), schema)


def ownership(candidates: DataFrame, owner: Column, repository: Column) -> DataFrame:
    """(hash, n_owners, n_repositories, n_found) of each value found anywhere.

    Counts go up in two steps, by value, repository and owner, then by value, each combined
    before its shuffle: a value copied into a third of all rows costs a task one row.
    """
    each = candidates.select(
        owner.alias("_owner"), repository.alias("_repo"), F.explode("spans").alias("_s")
    ).select("_owner", "_repo", F.sha2(F.col("_s.value"), 256).alias("hash"))
    pairs = each.groupBy("hash", "_owner", "_repo").agg(F.count("*").alias("_n"))
    owners = pairs.groupBy("hash", "_owner").agg(F.sum("_n").alias("_n"), F.count("*").alias("_repos"))
    return owners.groupBy("hash").agg(
        F.count("*").alias("n_owners"), F.sum("_repos").alias("n_repositories"), F.sum("_n").alias("n_found")
    )


def pair_key(*columns: str) -> Column:
    """One text for several columns; nulls and other pairs of values never give the same text."""
    parts = [F.coalesce(F.concat(F.length(c).cast("string"), F.lit("="), F.col(c)), F.lit("-")) for c in columns]
    return F.concat_ws(";", *parts)


def classified_spans(
    df: DataFrame, text: str, key: str, owner: str, repository: Column,
    example_owners: int = EXAMPLE_OWNERS, example_repositories: int = EXAMPLE_REPOSITORIES,
) -> DataFrame:
    """One row for each row of ``df``: key and ``spans``, an array of (kind, start, end, hash,
    n_owners, n_repositories, n_found, live), by start, then kind.

    A span is live if fewer than ``example_owners`` owners hold its value and it stands in fewer than
    ``example_repositories`` repositories. Spans of the kind added by this method stay only if
    live. Null owners count as one owner, null repositories as one repository; null or empty texts
    have no spans; rows with equal or null keys are kept apart. Values themselves are not
    returned, only their hashes. Other columns are ignored; an empty table gives no rows.
    """
    found = with_candidates(df.select(F.col(key).alias("_key"), F.col(owner).alias("_own"), repository.alias("_repo"), F.col(text).alias("_txt")), "_txt", ["_key", "_own", "_repo"])
    found = numbered(found, "_row", "candidates", keep=True)
    owner_key = F.coalesce(F.concat(F.lit("o"), F.col("_own").cast("string")), F.lit("-"))
    repo_key = F.coalesce(F.concat(F.lit("r"), F.col("_repo").cast("string")), F.lit("-"))
    hits = found.where(F.size("spans") > 0)
    counts = ownership(hits, owner_key, repo_key)
    spans = (
        hits.select("_row", F.explode("spans").alias("_s"))
        .select("_row", "_s.kind", "_s.start", "_s.end", F.sha2(F.col("_s.value"), 256).alias("hash"))
        .join(counts, "hash")
        .withColumn("live", (F.col("n_owners") < example_owners) & (F.col("n_repositories") < example_repositories))
        .where((F.col("kind") != LIVE) | F.col("live"))
    )
    order = F.create_map(*[F.lit(x) for i, k in enumerate((*KINDS, LIVE)) for x in (k, i)])
    per_row = spans.groupBy("_row").agg(
        F.sort_array(F.collect_list(F.struct("start", order[F.col("kind")].alias("rank"), "end", "kind", "hash", "n_owners", "n_repositories", "n_found", "live"))).alias("spans")
    )
    return (
        found.select("_row", F.col("_key").alias(key))
        .join(per_row, "_row", "left")
        .select(key, "_row", F.coalesce("spans", F.array().cast(per_row.schema["spans"].dataType)).alias("spans"))
    )


def _joined(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


@settled
def op7_ownership_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Spans of every document; a source is an owner, its texts of one language a repository."""
    docs = read_table(spark, sf_dir, "documents")
    out = classified_spans(docs, "text", "doc_id", "source", pair_key("source", "lang"))
    base = F.filter("spans", lambda s: s["kind"] != LIVE)
    of = lambda k: F.size(F.filter("spans", lambda s: s["kind"] == k)).cast("long")
    return out.select(
        "doc_id",
        *[of(k).alias(f"n_{k}") for k in KINDS],
        F.sha2(_joined(base).cast("binary"), 256).alias("base_sha256"),
        _joined(F.col("spans")).alias("spans"),
        F.size(F.filter("spans", lambda s: s["live"])).cast("long").alias("n_live"),
    )


def _parted(df: DataFrame, text: str, with_spans: bool) -> DataFrame:
    """Rows of ``df`` whose texts hold candidates of any kind, or the others."""
    schema = df.schema

    def pick(batches):
        for b in batches:
            texts = b.column(b.schema.get_field_index(text))
            hit = pc.fill_null(pc.match_substring_regex(texts, _ANY), False).to_numpy(zero_copy_only=False).copy()
            for i in hit.nonzero()[0].tolist():
                hit[i] = bool(find_spans(texts[i].as_py()))
            yield b.filter(pa.array(hit == with_spans))

    return df.mapInArrow(tidy(pick), schema)


def redacted(df: DataFrame, text: str, owner: str, repository: Column, mark: str = "[secret]") -> DataFrame:
    """``df`` with live spans of its texts replaced by ``mark``; examples stay. Overlapping
    spans are replaced as one. Spans meet their row by a written row number, so keys may be null
    or repeated. Only rows with candidates meet the spans in a join; the texts of the others
    are not shuffled. Null and empty texts stay as they are."""
    found = numbered(_parted(df, text, True), "_rid", "with-candidates", keep=True)
    spans = classified_spans(found, text, "_rid", owner, repository)
    live = spans.where(F.exists("spans", lambda s: s["live"])).select(
        F.col("_rid"), F.transform(F.filter("spans", lambda s: s["live"]), lambda s: F.struct(s["start"].alias("s"), s["end"].alias("e"))).alias("_live")
    )
    schema = df.schema

    def cover(batches):
        for b in batches:
            at = b.schema.get_field_index(text)
            texts = b.column(at).to_pylist()
            for i, cuts in enumerate(b.column(b.schema.get_field_index("_live")).to_pylist()):
                if not cuts:
                    continue
                t, parts, end = texts[i], [], 0
                for c in cuts:
                    if c["s"] >= end:
                        parts += [t[end : c["s"]], mark]
                    end = max(end, c["e"])
                texts[i] = "".join([*parts, t[end:]])
            yield pa.RecordBatch.from_arrays(
                [pa.array(texts, b.schema.field(at).type) if i == at else b.column(i) for i in range(len(schema))],
                [f.name for f in schema],
            )

    joined = found.join(live, "_rid", "left")
    return joined.select(*df.columns, "_live").mapInArrow(tidy(cover), schema).unionByName(_parted(df, text, False))


def secret_base_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Numbers of base spans of every document, which SQL can express too."""
    found = with_candidates(read_table(spark, sf_dir, "documents"), "text", ["doc_id"])
    # a second argument of the function would be the place in the array
    of = lambda k: F.size(F.filter("spans", lambda s: s["kind"] == k)).cast("long")
    return found.select("doc_id", *[of(k).alias(f"n_{k}") for k in KINDS])


def _counted(kind: str, pattern: str, group: int) -> str:
    found = f"regexp_extract_all(coalesce(text, ''), '{pattern.replace(chr(39), chr(39) * 2)}', {group})"
    return f"len(list_filter({found}, lambda x: length(x) >= {LEAST[kind]}))::BIGINT AS n_{kind}"


#: Letters of the names in either case, spelt out: a flag for all cases would fold other letters in.
_NAMES = re.sub("[a-z]", lambda m: f"[{m[0]}{m[0].upper()}]", PATTERNS["assign"].split(")")[0]) + ")"
BASE_SQL = f"""SELECT doc_id, {_counted('assign', _NAMES + PATTERNS['assign'].split(')', 1)[1], 2)}, {_counted('access', PATTERNS['access'], 0)},
  {_counted('hex', PATTERNS['hex'], 0)} FROM documents"""
