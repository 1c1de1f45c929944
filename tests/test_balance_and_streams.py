import itertools

import pytest

from freqsketch.functions.hashing import with_cells
from freqsketch.operators.build import build
from freqsketch.plans import balance as P
from freqsketch.sources.storage import stream, table
from freqsketch.spec import SketchSpec
from freqsketch.streaming.windows import drain, row_owned_stream, unpack_rows

SPEC = SketchSpec(4, 61)


def test_one_step_balances():
    fast, slow = P.rebalance(512, 512, 512 / 4.0, 512 / 1.0)
    assert fast / slow == pytest.approx(4.0) and fast + slow == 1024
    assert P.rebalance(fast, slow, fast / 4.0, slow / 1.0) == pytest.approx((fast, slow))


def test_clamps_and_guards():
    assert P.rebalance(512, 512, 4, 1) == (512, 512)
    assert P.rebalance(512, 512, 0, 1) == (512, 512)
    assert P.rebalance(0, 0, 1, 1) == (0, 0)


def test_controller_freezes():
    c = P.SplitController(1024, warmup=3)
    for t in ((1.0, 1.8), (1.0, 1.1), (1.0, 1.0)):
        c.observe(*t)
    kept = c.share()
    c.observe(1.0, 100.0)
    assert c.frozen and c.share() == kept and sum(kept) == 1024
    assert P.PhaseControllers(64).hashing is not P.PhaseControllers(64).updating


@pytest.mark.parametrize("fast,slow,depth", list(itertools.product([0, 1, 7, 658], [0, 1, 366], [1, 2, 7, 8])))
def test_two_stage_covers_once(spark, fast, slow, depth):
    rows = P.two_stage_plan(spark, 1, fast, slow, depth).collect()
    seen = [(r.sketch_row, p) for r in rows for p in range(r.from_pos, r.to_pos)]
    assert len(seen) == len(set(seen)) == (fast + slow) * depth
    for stage in (1, 2):
        workers = [r.worker_id for r in rows if r.stage == stage]
        assert len(workers) == len(set(workers))  # no worker on two rows, no row with two workers


@pytest.mark.parametrize("n,batch,depth,workers", [(10_000, 1024, 8, 3), (5, 1024, 8, 8), (1, 1, 1, 4), (100, 7, 3, 2)])
def test_static_plan_covers_once(spark, n, batch, depth, workers):
    rows = P.static_plan(spark, n, batch, depth, workers).collect()
    items = [p for r in rows if r.phase == "hash" for p in range(r.first, r.last + 1)]
    assert sorted(items) == list(range(n))
    owned = [p for r in rows if r.phase == "update" and r.batch_id == 0 for p in range(r.first, r.last + 1)]
    assert sorted(owned) == list(range(depth))


def test_dynamic_plan_follows_speed():
    out = P.dynamic_plan(50, 4, [1, 4])
    fast = sum(w == 0 for _, w, _, _ in out)
    assert fast == 40 and max(e for *_, e in out) == 160


def test_trace_settles(spark):
    t = P.rebalance_trace(spark).where("batch_id >= 30").groupBy("phase").avg("f2s").collect()
    got = {r[0]: r[1] for r in t}
    assert got["hash"] == pytest.approx(4.0, rel=0.03) and got["update"] == pytest.approx(1.8, rel=0.03)
    assert P.makespan(1, [1.8] * 4 + [1] * 4, False)[0] / P.makespan(1, [1.8] * 4 + [1] * 4, True)[0] == pytest.approx(1.4)


def test_stream_state_over_several_files(spark, sf, tmp_path):
    ev = table(spark, sf, "events")
    for k in range(4):  # one file after the other, as times order them
        ev.where(f"event_id % 4 = {k}").coalesce(1).write.mode("append").parquet(str(tmp_path / "events.parquet"))
    s = stream(spark, str(tmp_path), "events")
    got = unpack_rows(drain(row_owned_stream(s, "user_id", SPEC), "t", "update"))
    want = build(ev, "user_id", SPEC)
    assert got.exceptAll(want).count() == want.exceptAll(got).count() == 0


def test_cells_of_nothing(spark):
    assert with_cells(spark.createDataFrame([], "item long"), "item", SPEC).count() == 0


def test_measured_times_move_the_split(spark):
    """Slow workers that hash eight times over get less and less of a batch."""
    from freqsketch.streaming.balance import BalancedBuilder

    builder = BalancedBuilder(spark, SPEC, 1 << 18, pace={"hash": 8})
    df = spark.range(1 << 18).withColumnRenamed("id", "item")
    for k in range(4):
        builder.add(df, "item", k)
    trace = [r for r in builder.trace_rows().collect() if r.phase == "hash"]
    assert trace[0].f2s == 1.0 and trace[0].t_slow > 2 * trace[0].t_fast
    assert all(r.f2s > 1.8 for r in trace[2:])
    want = build(df.unionByName(df).unionByName(df).unionByName(df), "item", SPEC)
    got = builder.cells()
    assert got.exceptAll(want).count() == want.exceptAll(got).count() == 0


def test_a_batch_that_comes_again_counts_once(spark):
    from freqsketch.streaming.balance import BalancedBuilder

    builder = BalancedBuilder(spark, SPEC, 64)
    df = spark.range(100).withColumnRenamed("id", "item")
    builder.add(df, "item", 0)
    builder.add(df, "item", 0)
    want = build(df, "item", SPEC)
    assert builder.cells().exceptAll(want).count() == 0


def test_controller_freezes_in_the_loop():
    rows = P.closed_loop(64, warmup=30)
    held = {(p, s): {f for q, t, k, f, *_ in rows if (q, t) == (p, s) and k >= 30} for p, s, *_ in rows}
    assert all(len(v) == 1 for v in held.values())
