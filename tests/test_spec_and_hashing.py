import hashlib

import numpy as np
import pytest

from freqsketch.functions.hashing import columns, hash_tables, hash_values, merged_cells, separate_cells, with_cells
from freqsketch.functions.keys import item_key
from freqsketch.operators import measures as M
from freqsketch.spec import IncompatibleSketch, SketchSpec, depth_for, width_for


def test_sizes():
    assert [depth_for(0.003, r) for r in ("ln", "log2", "inverse", "fixed")] == [6, 9, 334, 8]
    assert [width_for(e, "prime_2_over_eps") for e in (1e-3, 1e-4, 1e-5)] == [2003, 20011, 200003]
    assert [SketchSpec.preset(s).width for s in ("small", "medium", "large")] == [2003, 20071, 200003]
    assert SketchSpec.preset("small").delta_bound() == pytest.approx(0.00386, abs=1e-4)
    with pytest.raises(ValueError):
        SketchSpec(0, 5)


def test_memory_example():
    s = SketchSpec.preset("small")
    assert M.memory_bits(s, 1 << 30, 8, "partials") == 3_845_760
    assert M.memory_bits(s, 1 << 30, 8, "row_owned") == 570_832
    assert [M.table_bytes(SketchSpec(8, w), 4) for w in (2003, 20071, 200003)] == [64_096, 642_272, 6_400_096]


def test_golden_hashes():
    assert hash_tables(8, 4, 42)[0, :3, 0].tolist() == [2839233389, 3420221422, 3837211556]
    assert columns(np.array([0, 7]), SketchSpec()).tolist() == [
        [44, 1944, 1339, 1468, 1950, 1917, 1462, 1727],
        [886, 768, 1201, 144, 1498, 1952, 695, 947],
    ]
    wide = columns(np.array([5 * 2**32 + 7, -5, 2**62 + 1]), SketchSpec(item_bits=64))
    assert wide[:, :2].tolist() == [[528, 1465], [1914, 1431], [1050, 417]]


@pytest.mark.parametrize("depth,bits", [(1, 32), (3, 32), (8, 32), (8, 64), (5, 64)])
def test_layouts_agree(depth, bits):
    spec = SketchSpec(depth, 977, 9, bits)
    x = np.random.default_rng(0).integers(-(2**62), 2**62, 20_000)
    values = [hash_values(x, spec, layout) for layout in ("paired", "merged", "separate")]
    assert (values[0] == values[1]).all() and (values[1] == values[2]).all()
    assert (columns(x, spec) == values[1] % 977).all()
    one = int(x[3]) & (2**64 - 1)
    h = 0
    for c in range(spec.chars):
        h ^= int(hashlib.md5(f"9:0:{c}:{(one >> (8 * c)) & 255}".encode()).hexdigest()[:8], 16)
    assert values[0][3, 0] == h


def test_relational_layouts(spark):
    spec = SketchSpec(5, 101)
    items = spark.range(300).withColumnRenamed("id", "item")
    rows = [set(map(tuple, f.collect())) for f in (separate_cells(spark, items, "item", spec), merged_cells(spark, items, "item", spec), with_cells(items, "item", spec))]
    assert rows[0] == rows[1] == rows[2]


def test_uniformity():
    spec = SketchSpec(4, 64)
    c = columns(np.arange(64_000), spec)
    for r in range(4):
        n = np.bincount(c[:, r], minlength=64)
        assert ((n - 1000) ** 2 / 1000).sum() < 130  # 63 degrees of freedom


def test_keys(spark):
    from pyspark.sql import functions as F

    df = spark.sql("SELECT 1Y a, 'x' s, DATE'2024-01-02' d, 1.50BD dec, -0.0D z, 0.0D z2, named_struct('p', 1, 'q', 'r') st, CAST(NULL AS STRING) n")
    got = df.select(*[item_key(df, c, nulls="item").alias(c) for c in df.columns]).first()
    assert got.a == 1 and got.d == 19724 and got.dec == 150 and got.z == got.z2 and got.n == -1
    assert got.s == int(hashlib.md5(b"x").hexdigest()[:8], 16)
    with pytest.raises(TypeError):
        item_key(df.select(F.array(F.lit(1)).alias("x")), "x")


def test_incompatible():
    with pytest.raises(IncompatibleSketch):
        SketchSpec().require_same(SketchSpec(seed=1))
    SketchSpec(eps=0.1).require_same(SketchSpec(eps=0.2))
