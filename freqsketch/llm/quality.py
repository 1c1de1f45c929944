"""Quality rules by robust multivariate outliers (operator 8).

Word and line statistics of each text, then minimum-covariance-determinant estimates of
their centre and spread for each language and source, and rejection by Mahalanobis distance.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import byte_slices, read_table, saved, segment_hash, settled, text_buffer, tidy, word_bounds, written
from .shared_files import read_groups

#: Characters counted as symbols.
SYMBOLS = b"#*$%&|<>"
WINDOW = 5
MIN_WORDS = 10
MAX_REPEAT_PERCENT = 20

#: Share of a group's rows that the estimates rest on.
SUPPORT = 0.75
#: Rows by which a language's estimates count in those of its groups, and those of all rows in
#: a language's: one rule for groups of every size.
SHRINK = 50.0
#: Concentration steps stop when no group's determinant falls any more; more than so many
#: mean that something is wrong, for each step lowers it.
MOST_STEPS = 40
#: A row is rejected beyond the upper fence of its group's own logarithms of squared distances:
#: the third quartile and so many times the distance between the quartiles.
FENCE = 1.5
#: Squared distances are counted in bins of this width of their natural logarithm.
BIN = 0.05
#: Steps in which statistics are counted for the quantiles of the start.
GRAIN = 0.01

#: The transformed statistics, and the least standard deviation of each: what one more word, sign
#: or line does to the statistic of a text of usual length.
FLOORS = {
    "f_words": 0.3,
    "f_word_len": 0.05,
    "f_symbols": 0.3,
    "f_dup_lines": 0.5,
    "f_repeat": 0.5,
    "f_stutter": 0.3,
}
FEATURES = tuple(FLOORS)
BASE_COLUMNS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
STAT_COLUMNS = (*BASE_COLUMNS, "n_stutter")


def _repeats(keys: np.ndarray, row: np.ndarray, n_rows: int) -> np.ndarray:
    """True where a (row, key) occurs twice or more."""
    if not len(keys):
        return np.zeros(0, bool)
    k = keys + row.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    order = np.argsort(k)
    s = k[order]
    same = s[1:] == s[:-1]
    twice = np.zeros(len(s), bool)
    twice[1:] |= same
    twice[:-1] |= same
    out = np.zeros(len(s), bool)
    out[order] = twice
    return out


_SYMBOL = np.zeros(256, bool)
_SYMBOL[list(SYMBOLS)] = True


def text_statistics(raw: np.ndarray, offsets: np.ndarray) -> dict[str, np.ndarray]:
    """The statistics of STAT_COLUMNS for rows of UTF-8 bytes."""
    n = len(offsets) - 1
    starts, ends, rows = word_bounds(raw, offsets)
    words = np.bincount(rows, minlength=n)

    def per_row(flags: np.ndarray) -> np.ndarray:
        total = np.zeros(len(raw) + 1, np.int64)
        np.cumsum(flags, out=total[1:])
        return total[offsets[1:]] - total[offsets[:-1]]

    from .common import _BLANK

    chars = per_row(((raw & 0xC0) != 0x80) & ~_BLANK[raw])
    symbols = per_row(_SYMBOL[raw])

    # lines that hold a word and equal an earlier line of their row
    breaks = np.flatnonzero(raw == 0x0A)
    line_start = np.union1d(offsets[:-1], breaks + 1)
    line_start = line_start[line_start < len(raw)]
    bounds = np.union1d(line_start, offsets[-1:])
    line_end = bounds[1:].copy() if len(line_start) else np.zeros(0, np.int64)
    if len(line_start):
        line_end[raw[line_end - 1] == 0x0A] -= 1
    first_word = np.searchsorted(starts, line_start)
    has_word = (first_word < len(starts)) & (starts[np.minimum(first_word, len(starts) - 1)] < line_end) if len(starts) else np.zeros(len(line_start), bool)
    ls, le = line_start[has_word], line_end[has_word]
    lrow = np.searchsorted(offsets, ls, "right") - 1
    key = segment_hash(raw, ls, le) + lrow.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    _, first = np.unique(key, return_index=True)
    later = np.ones(len(key), bool)
    later[first] = False
    dup_lines = np.bincount(lrow[later], minlength=n)

    # words inside a window of WINDOW words that occurs twice or more in its row
    h = segment_hash(raw, starts, ends)
    repeat = np.zeros(len(h), bool)
    m = len(h) - WINDOW + 1
    if m > 0:
        win = np.zeros(m, np.uint64)
        for k in range(WINDOW):
            win = win * np.uint64(0xD6E8FEB86659FD93) + h[k : k + m]
        whole = rows[:m] == rows[WINDOW - 1 :]
        at = np.flatnonzero(whole)
        at = at[_repeats(win[at], rows[at], n)]
        for k in range(WINDOW):
            repeat[at + k] = True
    repeated = np.bincount(rows[repeat], minlength=n)
    # words that equal the word before them
    again = np.zeros(len(h), bool)
    again[1:] = (h[1:] == h[:-1]) & (rows[1:] == rows[:-1])
    stutter = np.bincount(rows[again], minlength=n)
    return dict(zip(STAT_COLUMNS, (words, chars, symbols, dup_lines, repeated, stutter)))


def with_statistics(df: DataFrame, text: str, keep: list[str]) -> DataFrame:
    """Columns of ``keep`` and the statistics of the text, one row for each row, as ``q_<statistic>``
    so that they meet no column of the input. Null texts have no words, signs and lines."""
    picked = df.select(*keep) if text in keep else df.select(*keep, text)
    fields = picked.schema.fields[: len(keep)]
    schema = ", ".join([f"`{f.name}` {f.dataType.simpleString()}" for f in fields] + [f"q_{c} long" for c in STAT_COLUMNS])

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            raw, off = text_buffer(b.column(b.schema.get_field_index(text)))
            for lo, hi in byte_slices(off):
                stats = text_statistics(raw[off[lo] : off[hi]], off[lo : hi + 1] - off[lo])
                part = b.slice(lo, hi - lo)
                yield pa.RecordBatch.from_arrays(
                    [part.column(part.schema.get_field_index(f.name)) for f in fields]
                    + [pa.array(stats[c].astype(np.int64)) for c in STAT_COLUMNS],
                    [f.name for f in fields] + [f"q_{c}" for c in STAT_COLUMNS],
                )

    return picked.mapInArrow(tidy(count), schema)


def _features() -> dict[str, Column]:
    """Statistics as shares and logarithms, so that their bulk is near to normal."""
    n = F.greatest(F.col("q_n_words"), F.lit(1)).cast("double")
    share = lambda c: F.log1p(100.0 * F.col(c) / n)
    return {
        "f_words": F.log1p(F.col("q_n_words").cast("double")),
        "f_word_len": F.log1p(F.col("q_word_chars") / n),
        "f_symbols": share("q_n_symbols"),
        "f_dup_lines": share("q_n_dup_lines"),
        "f_repeat": share("q_n_repeat_words"),
        "f_stutter": share("q_n_stutter"),
    }


D = len(FEATURES)
UPPER = [(i, j) for i in range(D) for j in range(i, D)]
_FLOOR = np.array(list(FLOORS.values()))
_SCHEMA = pa.schema([("_g", pa.string()), ("_start", pa.int32()), ("_n", pa.int64()), ("centre", pa.list_(pa.float64())),
                     ("inverse", pa.list_(pa.float64())), ("_det", pa.float64()), ("_open", pa.bool_())])
_DDL = "_g string, _start int, _n long, centre array<double>, inverse array<double>, _det double, _open boolean"
#: Sums that a task has made for one group and start: places (bins, or statistic and value) and
#: numbers for each, with the estimates they rest on.
_PART = pa.schema([("_g", pa.string()), ("_start", pa.int32()), ("at", pa.binary()), ("sums", pa.binary()), ("old", pa.binary())])
_PART_DDL = "_g string, _start int, at binary, sums binary, old binary"


def _packed(centre: np.ndarray, inverse: np.ndarray, det: float, n: int) -> bytes:
    return np.concatenate([centre, inverse.ravel(), [det, n]]).tobytes()


def _unpacked(raw: bytes) -> tuple[np.ndarray, np.ndarray, float, int]:
    v = np.frombuffer(raw)
    return v[:D], v[D : D + D * D].reshape(D, D), float(v[-2]), int(v[-1])


def _row(g: str, start: int, n: int, centre: np.ndarray, spread: np.ndarray, det: float, open_: bool) -> dict:
    inverse = np.linalg.inv(spread).ravel().tolist()
    return {"_g": g, "_start": start, "_n": n, "centre": centre.tolist(), "inverse": inverse, "_det": det, "_open": open_}


def _full(total: np.ndarray) -> np.ndarray:
    """Symmetric matrix of an upper triangle."""
    out = np.zeros((D, D))
    for (i, j), v in zip(UPPER, total):
        out[i, j] = out[j, i] = v
    return out


def _parent(g: str) -> str:
    """A group's language and a language's ``*``, all rows; see ``_group_key``."""
    if g[0] == "=" or g == "*":
        return "*" if g[0] == "=" else ""
    size, rest = g.split(":", 1)
    return "=" + rest[: int(size)]


def _logs(x: np.ndarray, centre: np.ndarray, inverse: np.ndarray) -> np.ndarray:
    """Logarithms of squared distances, each row from the centre of its own group."""
    diff = x - centre
    return np.log(np.maximum(np.einsum("ij,ijk,ik->i", diff, inverse, diff), 1e-9))


class _Sums:
    """Sums by (group, start, place), which stay as small as the groups and places seen."""

    def __init__(self, width: int):
        self.width, self.names, self.held, self.n = width, {}, [], 0

    def add(self, names: list[str], code: np.ndarray, start: int, place: np.ndarray, values: np.ndarray) -> None:
        of = np.array([self.names.setdefault(g, len(self.names)) for g in names], np.int64)
        self.held.append(self._combined((of[code] * 2 + start) * (1 << 32) + (place + (1 << 31)), values))
        self.n += len(self.held[-1][0])
        if self.n > 1 << 18:
            self._combine()

    @staticmethod
    def _combined(key: np.ndarray, values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        order = np.argsort(key, kind="stable")
        key = key[order]
        first = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.zeros(0, np.int64)
        return key[first], np.add.reduceat(values[order], first, 0) if len(key) else values

    def _combine(self) -> None:
        self.held = [self._combined(*(np.concatenate(c) for c in zip(*self.held)))]
        self.n = len(self.held[0][0])

    def batches(self, old: dict) -> Iterator[pa.RecordBatch]:
        if not self.held:
            return
        self._combine()
        key, values = self.held[0]
        owner = key >> 32
        cuts = np.flatnonzero(np.diff(owner, prepend=-1, append=-1))
        names = list(self.names)
        rows = []
        for lo, hi in zip(cuts, cuts[1:]):
            g, start = names[owner[lo] >> 1], int(owner[lo] & 1)
            at = ((key[lo:hi] & 0xFFFFFFFF) - (1 << 31)).astype("<i8")
            rows.append({"_g": g, "_start": start, "at": at.tobytes(), "sums": values[lo:hi].astype("<f8").tobytes(), "old": old.get((g, start))})
        yield pa.RecordBatch.from_pylist(rows, _PART)


def _added(table: pa.Table, width: int) -> Iterator[tuple[int, np.ndarray, np.ndarray, bytes]]:
    """(start, places in order, sums, old estimates) of all tasks' parts of one group."""
    for start in sorted(set(table.column("_start").to_pylist())):
        mine = [r for r in table.to_pylist() if r["_start"] == start]
        at = np.concatenate([np.frombuffer(r["at"], "<i8") for r in mine])
        sums = np.concatenate([np.frombuffer(r["sums"], "<f8").reshape(-1, width) for r in mine])
        yield start, *_Sums._combined(at, sums), mine[0]["old"]


def _levels(b: pa.RecordBatch) -> Iterator[tuple[list[str], np.ndarray]]:
    """(names, number of the name for each row): groups, languages, all rows."""
    for c in (b.column(0), b.column(1)):
        d = c.dictionary_encode()
        yield d.dictionary.to_pylist(), d.indices.to_numpy()
    yield ["*"], np.zeros(len(b), np.int64)


def _points(b: pa.RecordBatch) -> np.ndarray:
    return np.stack([b.column(i + 2).to_numpy() for i in range(D)], 1)


class _Table:
    """Rows of a written table by group, read by a task as it meets the groups: of a table of any
    size a task holds the groups that it sees."""

    def __init__(self, uri: str, where: str | None = None):
        self.uri, self.where, self.rows = uri, where, {}

    def of(self, names: list[str]) -> list[list[dict]]:
        new = sorted(set(names) - self.rows.keys())
        if new:
            self.rows |= {g: [] for g in new}
            for r in read_groups(self.uri, "_g", new):
                if self.where is None or r[self.where]:
                    self.rows[r["_g"]].append(r)
        return [self.rows[g] for g in names]


def _estimates_of(found: list[list[dict]], start: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(has any, centre, inverse) for each name."""
    pick = [next((r for r in rows if r["_start"] == start), None) for rows in found]
    centre = np.array([r["centre"] if r else [0.0] * D for r in pick]).reshape(-1, D)
    inverse = np.array([r["inverse"] if r else [0.0] * D * D for r in pick]).reshape(-1, D, D)
    return np.array([r is not None for r in pick]), centre, inverse


def _starts(good: DataFrame) -> str:
    """Two first estimates for each group: medians with the middle 80 % of each statistic alone,
    and the same with the correlations of the rows' directions from the medians."""

    def count(batches):
        sums = _Sums(1)
        for b in batches:
            steps = np.rint(_points(b) / GRAIN).astype(np.int64)
            for names, code in _levels(b):
                for i in range(D):
                    sums.add(names, code, 0, steps[:, i] * 8 + i, np.ones((len(b), 1)))
        yield from sums.batches({})

    def middle(table: pa.Table) -> pa.Table:
        ((_, at, sums, _),) = _added(table, 1)
        value, which, c = (at >> 3) * GRAIN, at & 7, sums[:, 0]
        centre, spread = np.zeros(D), np.zeros(D)
        for k in range(D):
            v, run = value[which == k], np.cumsum(c[which == k])
            low, centre[k], high = (v[np.searchsorted(run, s * run[-1])] for s in (0.1, 0.5, 0.9))
            # 2.563 standard deviations of a normal lie between its tenth and ninetieth percent
            spread[k] = max((high - low) / 2.563, _FLOOR[k])
        n = int(c[which == 0].sum())
        return pa.Table.from_pylist([_row(table.column("_g")[0].as_py(), 0, n, centre, np.diag(spread**2), np.inf, True)], _SCHEMA)

    plain = saved(good.mapInArrow(tidy(count), _PART_DDL).groupBy("_g").applyInArrow(middle, _DDL), "quality-start")

    def turn(batches):
        sums, table, old = _Sums(len(UPPER)), _Table(plain), {}
        for b in batches:
            x = _points(b)
            for names, code in _levels(b):
                found = table.of(names)
                _, centre, inverse = _estimates_of(found, 0)
                old |= {(g, 0): _packed(np.array(r["centre"]), np.array(r["inverse"]), 0.0, r["_n"]) for g, (r,) in zip(names, found)}
                z = (x - centre[code]) * np.sqrt(inverse[:, range(D), range(D)])[code]
                u = z / np.sqrt(np.maximum((z * z).sum(1, keepdims=True), 1e-12))
                sums.add(names, code, 0, np.zeros(len(b), np.int64), np.stack([u[:, i] * u[:, j] for i, j in UPPER], 1))
        yield from sums.batches(old)

    def both(table: pa.Table) -> pa.Table:
        ((_, _, sums, old),) = _added(table, len(UPPER))
        centre, inverse, _, n = _unpacked(old)
        scale = np.diag(inverse) ** -0.5
        turned = _full(sums[0] / n) * D * np.outer(scale, scale) + np.diag(_FLOOR**2)
        g = table.column("_g")[0].as_py()
        return pa.Table.from_pylist([_row(g, k, n, centre, m, np.inf, True) for k, m in enumerate((np.diag(scale**2), turned))], _SCHEMA)

    return saved(good.mapInArrow(tidy(turn), _PART_DDL).groupBy("_g").applyInArrow(both, _DDL), "quality-start")


def mcd_estimates(good: DataFrame, support: float = SUPPORT) -> str:
    """Minimum-covariance-determinant estimates (_g, _n, centre, inverse) of rows (group, language,
    FEATURES), for groups, languages and all rows; returns the folder of the table.

    From each of two deterministic starts, concentration steps: keep the share ``support`` of
    rows nearest to the present estimates, take their mean and covariance, and go on until the
    determinant falls no more; the start that ends with the smaller determinant is taken.

    A step reads all rows, never a sample. Tasks sum them by group and bin of distance, so what
    renews a group's estimates is its bins, however many rows the group has.
    """
    spark = good.sparkSession
    width = 1 + D + len(UPPER)
    est, done = _starts(good), []
    for _ in range(MOST_STEPS):
        now = est

        def count(batches):
            sums, table, old = _Sums(width), _Table(now, "_open"), {}
            for b in batches:
                x = _points(b)
                moments = np.concatenate([np.ones((len(x), 1)), x, np.stack([x[:, i] * x[:, j] for i, j in UPPER], 1)], 1)
                for names, code in _levels(b):
                    found = table.of(names)
                    old |= {(r["_g"], r["_start"]): _packed(np.array(r["centre"]), np.array(r["inverse"]), r["_det"], r["_n"]) for rows in found for r in rows}
                    for start in (0, 1):
                        has, centre, inverse = _estimates_of(found, start)
                        at = np.flatnonzero(has[code])
                        if len(at):
                            c = code[at]
                            place = np.floor(_logs(x[at], centre[c], inverse[c]) / BIN).astype(np.int64)
                            sums.add(names, c, start, place, moments[at])
            yield from sums.batches(old)

        def renew(table: pa.Table) -> pa.Table:
            g, rows = table.column("_g")[0].as_py(), []
            for start, _, sums, old in _added(table, width):
                run = np.cumsum(sums[:, 0])
                total = sums[: int(np.searchsorted(run, support * run[-1])) + 1].sum(0)
                mean = total[1 : 1 + D] / total[0]
                cov = _full(total[1 + D :] / total[0]) - np.outer(mean, mean) + np.diag(_FLOOR**2)
                det = float(np.linalg.slogdet(cov)[1])
                centre, inverse, before, n = _unpacked(old)
                if det < before - 1e-6:
                    rows.append(_row(g, start, n, mean, cov, det, True))
                else:
                    rows.append(_row(g, start, n, centre, np.linalg.inv(inverse), before, False))
            return pa.Table.from_pylist(rows, _SCHEMA)

        est = saved(good.mapInArrow(tidy(count), _PART_DDL).groupBy("_g").applyInArrow(renew, _DDL), "quality-step")
        done.append(est)
        if not spark.read.schema(_DDL).parquet(est).where("_open").limit(1).count():
            break
    ended = spark.read.schema(_DDL).parquet(*done).where("not _open")
    best = ended.groupBy("_g").agg(F.min_by(F.struct("_n", "centre", "inverse"), F.struct("_det", "_start")).alias("_e"))
    return saved(best.select("_g", F.lit(0).alias("_start"), "_e.*"), "quality-estimates")


def _limits(good: DataFrame, shrink: float, fence: float) -> DataFrame:
    """(_group, centre, inverse, _limit) of every group: estimates, quartiles of the logarithms of
    squared distances and the fence that follows, each drawn towards the language's and these
    towards those of all rows, as if the parents were ``shrink`` more rows."""
    spark = good.sparkSession
    est = mcd_estimates(good)
    weight = lambda r: r["_n"] / (r["_n"] + shrink)
    kind = pa.schema([("_g", pa.string()), ("_start", pa.int32()), ("_n", pa.int64()), ("centre", pa.list_(pa.float64())), ("inverse", pa.list_(pa.float64()))])

    def blend(batches):
        table = _Table(est)
        back = lambda r: (np.array(r["centre"]), np.linalg.inv(np.reshape(r["inverse"], (D, D))))

        def whole(r):
            c, m = back(r)
            up = _parent(r["_g"])
            if up:
                w, (pc, pm) = weight(r), whole(table.of([up])[0][0])
                c, m = w * c + (1 - w) * pc, w * m + (1 - w) * pm
            return c, m

        for b in batches:
            rows = []
            for r in b.to_pylist():
                c, m = whole(r)
                rows.append(r | {"centre": c.tolist(), "inverse": np.linalg.inv(m).ravel().tolist()})
            yield pa.RecordBatch.from_pylist(rows, kind)

    ddl = "_g string, _start int, _n long, centre array<double>, inverse array<double>"
    mixed = saved(spark.read.schema(ddl).parquet(est).mapInArrow(blend, ddl), "quality-blended")

    def count(batches):
        sums, table, old = _Sums(1), _Table(mixed), {}
        for b in batches:
            x = _points(b)
            for names, code in _levels(b):
                found = table.of(names)
                old |= {(g, 0): _packed(np.array(r["centre"]), np.array(r["inverse"]), 0.0, r["_n"]) for g, (r,) in zip(names, found)}
                _, centre, inverse = _estimates_of(found, 0)
                sums.add(names, code, 0, np.floor(_logs(x, centre[code], inverse[code]) / BIN).astype(np.int64), np.ones((len(b), 1)))
        yield from sums.batches(old)

    quarter = pa.schema([*kind, ("_q1", pa.float64()), ("_q3", pa.float64())])

    def cuts(table: pa.Table) -> pa.Table:
        ((_, at, sums, old),) = _added(table, 1)
        run = np.cumsum(sums[:, 0])
        q1, q3 = (float((at[np.searchsorted(run, s * run[-1])] + 0.5) * BIN) for s in (0.25, 0.75))
        centre, inverse, _, n = _unpacked(old)
        row = {"_g": table.column("_g")[0].as_py(), "_start": 0, "_n": n, "centre": centre.tolist(), "inverse": inverse.ravel().tolist(), "_q1": q1, "_q3": q3}
        return pa.Table.from_pylist([row], quarter)

    ddl += ", _q1 double, _q3 double"
    own = saved(good.mapInArrow(tidy(count), _PART_DDL).groupBy("_g").applyInArrow(cuts, ddl), "quality-quartiles")

    def limit(batches):
        table = _Table(own)

        def whole(r):
            q = np.array([r["_q1"], r["_q3"]])
            up = _parent(r["_g"])
            return weight(r) * q + (1 - weight(r)) * whole(table.of([up])[0][0]) if up else q

        for b in batches:
            rows = []
            for r in b.to_pylist():
                q1, q3 = whole(r)
                rows.append({"_group": r["_g"], "centre": r["centre"], "inverse": r["inverse"], "_limit": float(q3 + fence * (q3 - q1))})
            yield pa.RecordBatch.from_pylist(rows, pa.schema([("_group", pa.string()), kind.field("centre"), kind.field("inverse"), ("_limit", pa.float64())]))

    groups = spark.read.schema(ddl).parquet(own).where("not startswith(_g, '=') and _g <> '*'")
    return written(groups.mapInArrow(limit, "_group string, centre array<double>, inverse array<double>, _limit double"), "quality-limits", keep=True)


def _squared_distance() -> Column:
    diff = [F.col(f) - F.get(F.col("centre"), F.lit(i)) for i, f in enumerate(FEATURES)]
    total: Column = F.lit(0.0)
    for i, j in UPPER:
        term = F.get(F.col("inverse"), F.lit(i * D + j)) * diff[i] * diff[j]
        total = total + (term if i == j else term * 2)
    return F.greatest(total, F.lit(1e-9))


def base_rule() -> Column:
    """Too few words, or too many of them in repeated windows."""
    return (F.col("q_n_words") < MIN_WORDS) | (100 * F.col("q_n_repeat_words") > MAX_REPEAT_PERCENT * F.col("q_n_words"))


def quality_verdicts(
    df: DataFrame, lang: str = "lang", source: str = "source", fence: float = FENCE, shrink: float = SHRINK
) -> DataFrame:
    """Adds base_failed, distance_ratio and kept to rows with the columns of ``with_statistics``,
    which become STAT_COLUMNS. Input columns of these names are replaced.

    ``base_failed``: fewer than MIN_WORDS words, or more than MAX_REPEAT_PERCENT of them
    in repeated windows. Other rows are judged by their squared Mahalanobis distance from their
    group (language and source): beyond the upper fence of the logarithms of the group's own
    distances they are rejected; ``distance_ratio`` is the distance in units of that fence. A
    group of n rows weighs n / (n + ``shrink``) in its centre, spread and quartiles, its language
    the rest; a language is drawn towards all rows likewise. Estimates rest on the rows that
    pass the base rules. Nulls in language or source form groups of their own. Equal rows get equal
    verdicts. A table in which no row passes yields base verdicts alone, an empty one no rows.

    The rows are written once with their statistics; fits read the statistics alone, and the
    verdicts join the rows with the small table of limits, so no row is shuffled.
    """
    failed = base_rule()
    lang_key = F.coalesce(F.concat(F.lit("l"), F.col(lang)), F.lit("-"))
    source_key = F.coalesce(F.concat(F.lit("s"), F.col(source)), F.lit("-"))
    # the length of the language's key says where the source's begins
    group = F.concat(F.length(lang_key).cast("string"), F.lit(":"), lang_key, source_key)
    judged = df.withColumns({"_base": failed, "_lang": F.concat(F.lit("="), lang_key), "_group": group, **_features()})
    judged = written(judged, "quality-rows", keep=True)
    limits = _limits(judged.where("not _base").select("_group", "_lang", *FEATURES), shrink, fence)
    ratio = F.when(~F.col("_base") & F.col("centre").isNotNull(), _squared_distance() / F.exp("_limit"))
    out = judged.join(limits, "_group", "left").withColumn("_ratio", ratio)
    added = {**{c: F.col(f"q_{c}") for c in STAT_COLUMNS}, "base_failed": F.col("_base"), "distance_ratio": F.col("_ratio"),
             "kept": ~F.col("_base") & F.coalesce(F.col("_ratio") <= 1.0, F.lit(True))}
    stays = [c for c in df.columns if not c.startswith("q_") and c not in added]
    return out.select(*stays, *[v.alias(k) for k, v in added.items()])


@settled
def op8_robust_outliers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Statistics, base rule and verdict of every document; see ``quality_verdicts``."""
    docs = read_table(spark, sf_dir, "documents")
    out = quality_verdicts(with_statistics(docs, "text", ["doc_id", "lang", "source"]))
    return out.select("doc_id", *BASE_COLUMNS, "base_failed", "kept", "distance_ratio", "n_stutter")


def quality_base_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The statistics and the base rule of every document, which SQL can express too."""
    rows = with_statistics(read_table(spark, sf_dir, "documents"), "text", ["doc_id"])
    return rows.select("doc_id", *[F.col(f"q_{c}").alias(c) for c in STAT_COLUMNS], base_rule().alias("base_failed"))


_W = r"[^\x20\x09-\x0D]+"
BASE_SQL = f"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t, regexp_extract_all(coalesce(text, ''), '{_W}') AS w FROM documents),
l AS (SELECT doc_id, unnest(string_split(t, chr(10))) AS line FROM d),
lines AS (SELECT doc_id, count(*) - count(DISTINCT line) AS dup FROM l WHERE regexp_matches(line, '{_W}') GROUP BY doc_id),
pos AS (SELECT doc_id, unnest(w) AS x, generate_subscripts(w, 1) AS i FROM d),
win AS (SELECT doc_id, i, x, lag(x) OVER p AS before, {", ".join(f"lead(x, {k}) OVER p AS x{k}" for k in range(1, WINDOW))} FROM pos WINDOW p AS (PARTITION BY doc_id ORDER BY i)),
again AS (SELECT doc_id, unnest(list(i)) AS i FROM win WHERE x{WINDOW - 1} IS NOT NULL GROUP BY doc_id, x, {", ".join(f"x{k}" for k in range(1, WINDOW))} HAVING count(*) > 1),
covered AS (SELECT doc_id, count(DISTINCT i + k.range) AS n FROM again, range({WINDOW}) k GROUP BY doc_id),
stutter AS (SELECT doc_id, count(*) AS n FROM win WHERE x = before GROUP BY doc_id),
s AS (SELECT d.doc_id, len(w)::BIGINT AS n_words, coalesce(list_sum(list_transform(w, lambda x: length(x))), 0)::BIGINT AS word_chars,
    length(regexp_replace(t, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols, coalesce(lines.dup, 0)::BIGINT AS n_dup_lines,
    coalesce(covered.n, 0)::BIGINT AS n_repeat_words, coalesce(stutter.n, 0)::BIGINT AS n_stutter
  FROM d LEFT JOIN lines USING (doc_id) LEFT JOIN covered USING (doc_id) LEFT JOIN stutter USING (doc_id))
SELECT *, n_words < {MIN_WORDS} OR 100 * n_repeat_words > {MAX_REPEAT_PERCENT} * n_words AS base_failed FROM s
"""
