"""Building blocks of the SQL twins: the same hash functions and streams in plain SQL.

They start from md5 and joins, not from anything the Spark code computes.
"""

from __future__ import annotations

from freqsketch.spec import SketchSpec


def table_cte(spec: SketchSpec, name: str = "tab") -> str:
    """Random tables: (hash_id, char_pos, char_val, rnd)."""
    return f"""{name} AS (
  SELECT h.range AS hash_id, c.range AS char_pos, v.range AS char_val,
         ('0x' || substr(md5('{spec.seed}:' || h.range || ':' || c.range || ':' || v.range), 1, 8))::BIGINT AS rnd
  FROM range({spec.depth}) h, range({spec.chars}) c, range(256) v)"""


def hashed_cte(items: str, spec: SketchSpec, name: str = "hashed", tab: str = "tab", extra: str = "") -> str:
    """(item, hash_id, hv, sketch_col) of the distinct values of relation ``items``' column item."""
    hv = "t0.rnd"
    joins = f"JOIN {tab} t0 ON t0.char_pos = 0 AND t0.char_val = (i.item & 255)"
    for c in range(1, spec.chars):
        hv = f"xor({hv}, t{c}.rnd)"
        joins += f" JOIN {tab} t{c} ON t{c}.hash_id = t0.hash_id AND t{c}.char_pos = {c} AND t{c}.char_val = ((i.item >> {8 * c}) & 255)"
    return f"""{name} AS (
  SELECT i.item, t0.hash_id::INTEGER AS sketch_row, {hv} AS hv, ({hv} % {spec.width})::INTEGER AS sketch_col
  FROM (SELECT DISTINCT item FROM {items} WHERE item IS NOT NULL) i {joins})"""


def xor_sql(items: str, spec: SketchSpec) -> str:
    """(item, sketch_row, sketch_col) with one narrow row for a byte of an item, XORed by aggregation:
    for wide items, where a join for each byte would be too many."""
    return f"""WITH {table_cte(spec)}, bytes AS (SELECT item, c.range AS char_pos, (item >> (8 * c.range)) & 255 AS char_val FROM ({items}) i, range({spec.chars}) c)
  SELECT item, hash_id::INTEGER AS sketch_row, (bit_xor(rnd) % {spec.width})::INTEGER AS sketch_col
  FROM bytes JOIN tab USING (char_pos, char_val) GROUP BY item, hash_id"""


def counts_cte(stream: str, name: str = "counts") -> str:
    return f"{name} AS (SELECT item, count(*)::BIGINT AS cnt FROM {stream} WHERE item IS NOT NULL GROUP BY item)"


def cells_cte(spec: SketchSpec, counts: str = "counts", hashed: str = "hashed", name: str = "cells", keys: str = "") -> str:
    k = f"{keys}, " if keys else ""
    return f"""{name} AS (
  SELECT {k}sketch_row, sketch_col, sum(cnt)::BIGINT AS cnt FROM {counts} JOIN {hashed} USING (item) GROUP BY {k}sketch_row, sketch_col)"""


def sketch_ctes(stream_sql: str, spec: SketchSpec, p: str = "") -> str:
    """stream, counts, tab, hashed, cells over ``SELECT ... AS item``, names prefixed by ``p``."""
    return ",\n".join(
        [
            f"{p}stream AS ({stream_sql})",
            counts_cte(f"{p}stream", f"{p}counts"),
            table_cte(spec, f"{p}tab"),
            hashed_cte(f"{p}counts", spec, f"{p}hashed", f"{p}tab"),
            cells_cte(spec, f"{p}counts", f"{p}hashed", f"{p}cells"),
        ]
    )


def cells_sql(stream_sql: str, spec: SketchSpec) -> str:
    return f"WITH {sketch_ctes(stream_sql, spec)} SELECT sketch_row, sketch_col, cnt FROM cells"


def estimates_cte(asked: str, spec: SketchSpec, p: str = "", name: str = "est") -> str:
    """(item, estimate) of relation ``asked`` against ``{p}cells``; hashes it again."""
    return (
        hashed_cte(asked, spec, f"{name}_h", f"{p}tab")
        + f""",
{name} AS (SELECT h.item, min(coalesce(c.cnt, 0))::BIGINT AS estimate FROM {name}_h h
  LEFT JOIN {p}cells c USING (sketch_row, sketch_col) GROUP BY h.item)"""
    )


def zipf_sql(n: int, alpha: float, seed: int = 7, table: str = "events", pos: str = "event_id") -> str:
    return f"""SELECT e.pos, t.r AS item FROM (
    SELECT {pos} AS pos, ('0x' || substr(md5('{seed}:' || {pos}), 1, 15))::BIGINT %
      (SELECT sum(round(1e9 * pow(range, -{alpha}))::BIGINT)::BIGINT FROM range(1, {n + 1})) AS u FROM {table}) e
  JOIN (SELECT range AS r, sum(w) OVER (ORDER BY range) - w AS lo, sum(w) OVER (ORDER BY range) AS hi
        FROM (SELECT range, round(1e9 * pow(range, -{alpha}))::BIGINT AS w FROM range(1, {n + 1}))) t
  ON e.u >= t.lo AND e.u < t.hi"""


WORDS_SQL = """SELECT word, count(*)::BIGINT AS cnt FROM (
  SELECT unnest(string_split_regex(lower(text), '[^a-z]+')) AS word FROM documents) WHERE word <> '' GROUP BY word"""


def word_key(word: str = "word") -> str:
    return f"('0x' || substr(md5({word}), 1, 8))::BIGINT"
