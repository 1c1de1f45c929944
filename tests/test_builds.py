import numpy as np
import pytest
from pyspark.sql import functions as F

from freqsketch.functions.hashing import columns
from freqsketch.operators import algebra as A
from freqsketch.operators import build as B
from freqsketch.operators import query as Q
from freqsketch.plans.planner import build_planned
from freqsketch.sources.generators import power_law_items, zipf_stream
from freqsketch.spec import IncompatibleSketch, SketchSpec

SPEC = SketchSpec(4, 61)


def reference(items, spec=SPEC):
    out = {}
    for x in items:
        for r, c in enumerate(columns(np.array([x]), spec)[0]):
            out[(r, int(c))] = out.get((r, int(c)), 0) + 1
    return out


def cells(df):
    return {(r.sketch_row, r.sketch_col): r.cnt for r in df.collect()}


@pytest.fixture(scope="module")
def items():
    return [int(x) for x in np.random.default_rng(5).zipf(1.3, 3000) % 500]


@pytest.fixture(scope="module")
def frame(spark, items):
    return spark.createDataFrame([(i, x) for i, x in enumerate(items)], "pos long, item long").repartition(5)


@pytest.mark.parametrize("strategy", B.STRATEGIES)
def test_strategies_agree(frame, items, strategy):
    if strategy == "two_stage":
        got = B.build_two_stage(frame, "pos", "item", SPEC, 70, 31)
    else:
        got = B.build(frame, "item", SPEC, strategy)
    assert cells(got) == reference(items)


@pytest.mark.parametrize("segments", [1, 3, 7])
@pytest.mark.parametrize("batch", [1, 7, 1000, 1024])
def test_owner_segments_and_batches(frame, items, segments, batch):
    assert cells(B.build(frame, "item", SPEC, "row_owned", segments=segments, batch=batch)) == reference(items)


@pytest.mark.parametrize("spec", [SketchSpec(1, 61), SketchSpec(2, 1), SketchSpec(3, 5, hash_family="modular")])
def test_small_shapes(frame, items, spec):
    assert cells(B.build(frame, "item", spec)) == reference(items, spec)


def test_empty_null_and_weights(spark):
    empty = spark.createDataFrame([], "item long")
    nulls = spark.createDataFrame([(None,), (None,)], "item long")
    for s in ("serial", "partials", "row_owned", "combine_items", "shared_atomic"):
        assert cells(B.build(empty, "item", SPEC, s)) == {}
        assert cells(B.build(nulls, "item", SPEC, s)) == {}
    w = spark.createDataFrame([(3, 2), (3, None), (9, 5)], "item long, w long")
    assert cells(B.build(w, "item", SPEC, weight=F.col("w"))) == reference([3, 3] + [9] * 5)


def test_estimates_never_fall_short(frame, items, spark):
    built = B.build(frame, "item", SPEC)
    asked = spark.range(800).withColumnRenamed("id", "item")
    truth = {x: items.count(x) for x in range(800)}
    plain = {r.item: r.estimate for r in Q.estimate(built, asked, "item", SPEC).collect()}
    dense = {r.item: r.estimate for r in Q.estimate_dense(Q.dense_rows(built, SPEC), asked, "item", SPEC).collect()}
    assert plain == dense and all(plain[x] >= truth[x] for x in truth)
    corrected = Q.estimate_corrected(built, asked, "item", SPEC, len(items)).collect()
    assert all(r.estimate <= plain[r.item] for r in corrected)


def test_algebra(frame, items):
    a, b = frame.where("pos < 1000"), frame.where("pos >= 1000")
    x, y = B.build(a, "item", SPEC), B.build(b, "item", SPEC)
    whole = reference(items)
    assert cells(A.merge((x, SPEC), (y, SPEC))) == cells(A.merge((y, SPEC), (x, SPEC))) == whole
    assert cells(A.subtract(A.merge((x, SPEC), (y, SPEC)), y)) == reference(items[:1000])
    assert {r.total for r in A.row_totals(x).collect()} == {1000}
    assert A.difference(x, x).count() == 0
    with pytest.raises(IncompatibleSketch):
        A.merge((x, SPEC), (y, SketchSpec(4, 62)))
    dense = np.arange(8).reshape(2, 4)
    back, spec = A.unpack(A.pack(dense, SketchSpec(2, 4)))
    assert (back == dense).all() and spec == SketchSpec(2, 4)


def test_relaxed_model(frame, items):
    n = len(items)
    exact = reference(items)
    assert cells(B.build_relaxed(frame, "pos", "item", SPEC, 1, n)) == exact
    lossy = cells(B.build_relaxed(frame, "pos", "item", SPEC, 8, n))
    assert all(lossy[k] <= exact[k] for k in exact) and sum(lossy.values()) < sum(exact.values())


def test_loss_grows_with_skew(spark):
    pos = spark.range(20_000)
    spec, lost = SketchSpec(4, 2003), []
    for alpha in (0.0, 1.1, 1.5):
        s = zipf_stream(pos, "id", 1024, alpha)
        lost.append(80_000 - sum(cells(B.build_relaxed(s, "pos", "item", spec, 8, 20_000)).values()))
    assert lost[0] < lost[1] < lost[2]


def test_zipf_golden(spark):
    s = zipf_stream(spark.range(10_000), "id", 1024, 1.1)
    top = [r["count"] for r in s.groupBy("item").count().orderBy("item").limit(4).collect()]
    assert top == [1791, 813, 510, 407]
    p = power_law_items(spark.range(5000), "id", 100, 1.1).agg(F.min("item"), F.max("item")).first()
    assert p[0] == 1 and p[1] <= 100


def test_planner(frame, items, spark):
    built, plan = build_planned(frame, "item", SPEC)
    assert cells(built) == reference(items) and plan.strategy in ("partials", "combine_items", "row_owned")
    big = spark.range(200_000).select(F.col("id").alias("item"))
    assert build_planned(big, "item", SketchSpec(8, 2003))[1].strategy == "partials"
    assert build_planned(big.select((F.col("item") % 50).alias("item")), "item", SketchSpec(8, 2003))[1].strategy == "combine_items"


def test_one_table_beyond_any_task(frame, items, spark):
    """2 x 2^26 counters: no task may allocate the table, an owner has 2^22 of them."""
    spec = SketchSpec(2, 1 << 26)
    assert cells(B.build(frame, "item", spec, "row_owned", segments=16)) == reference(items, spec)
    wide = SketchSpec(8, 20071)
    built, plan = build_planned(frame, "item", wide, task_budget=1 << 19)
    assert plan.strategy == "row_owned" and cells(built) == reference(items, wide)


def test_row_owned_has_one_exchange(frame, capsys):
    B.build(frame, "item", SPEC, "row_owned", segments=3).explain()
    plan = capsys.readouterr().out.split("repartition")[0]
    assert plan.count("Exchange") <= 2  # the owners', and the fixture's own


@pytest.mark.parametrize("split", [(1.8, 1.0), (1.0, 0.0), (4.0, 1.0)])
@pytest.mark.parametrize("depth,segments", [(4, 1), (5, 3)])
def test_balanced_pairs_update_everything_once(frame, items, split, depth, segments):
    spec = SketchSpec(depth, 61)
    assert cells(B.build(frame, "item", spec, "row_owned_balanced", split=split, segments=segments, batch=100)) == reference(items, spec)


def test_costs_are_measured(frame):
    from freqsketch.operators.costs import COST_SCHEMA, spark_costs

    names = [c.split()[0] for c in COST_SCHEMA.split(", ")]
    got = dict(zip(names, spark_costs(B.build(frame, "item", SPEC, "row_owned"))))
    assert got["shuffle_write_bytes"] > 0 and got["stages"] >= 2 and got["tasks"] >= 5 and got["seconds"] > 0


def test_packed_sketch_keeps_its_identity():
    dense = np.arange(8).reshape(2, 4)
    raw = A.pack(dense, SketchSpec(2, 4, hash_family="modular"))
    back, spec = A.unpack(raw)
    assert spec.hash_family == "modular" and A.packed_total(raw) == 6
    with pytest.raises(IncompatibleSketch):
        SketchSpec(2, 4).require_same(spec)


def test_groups_of_any_size(spark):
    from freqsketch.sqlapi import sketch_per_group

    df = spark.range(3000).selectExpr("id % 3 AS g", "CASE WHEN id % 3 = 0 THEN 'a' END AS h", "id % 50 AS item")
    got = {r.g: A.unpack(bytes(r.sketch))[0] for r in sketch_per_group(df, ["g", "h"], "item", SPEC).collect()}
    for g in range(3):
        want = reference([x % 50 for x in range(g, 3000, 3)])
        assert {(r, c): v for r, row in enumerate(got[g].tolist()) for c, v in enumerate(row) if v} == want


def test_ranks_and_tiles(spark):
    from freqsketch.operators.ranks import tiles

    df = spark.range(103).selectExpr("(id * 37) % 103 AS k", "id % 4 AS v")
    got = {r.k: r.part for r in tiles(df, ["v", "k"], 10, "part").collect()}
    want = {r.k: r.part for r in df.selectExpr("k", "ntile(10) OVER (ORDER BY v, k) AS part").collect()}
    assert got == want


def test_scan_is_pruned(spark, sf, capsys):
    from freqsketch.workloads.relational import filter_then_sketch

    filter_then_sketch(spark, sf).explain("formatted")
    plan = capsys.readouterr().out
    assert "PushedFilters: [IsNotNull(l_shipdate)" in plan and "ReadSchema: struct<l_partkey:bigint,l_shipdate:timestamp_ntz>" in plan


def test_barrier_demonstrator(frame, items):
    assert cells(B.build_barrier(B.items_of(frame, "item"), SPEC, 2, batch=64)) == reference(items)


def test_grids(spark):
    from freqsketch.plans.planner import choose, explain_build
    from freqsketch.workloads.grid import owned_against_relaxed, time_grid

    got = time_grid(spark, 1 << 12, 1 << 8, 1, (1.1,), ("small",)).collect()
    assert len(got) == 4 and all(r.million_items_per_sec > 0 for r in got)
    assert owned_against_relaxed(spark, 1 << 12, 1 << 8, 1, (1.1,)).count() == 4
    assert "distinct" in explain_build(choose(spark.range(10).withColumnRenamed("id", "item"), "item", SPEC))
