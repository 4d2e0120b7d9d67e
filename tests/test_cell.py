"""The cell merge: case table, invariants, and agreement of the column form with the kernel."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from fadedhh.functions import cell
from fadedhh.operators.kernel import NumpySketch, merge_cells, reduce_by_key
from fadedhh.operators.params import SketchParams, dimension, implied, miss_bound


def plain_merge(a, b, k=2):
    """Dictionaries of counters, straight from the definition."""
    ma = min(a.values()) if len(a) == k else 0
    mb = min(b.values()) if len(b) == k else 0
    out = {i: f + b.get(i, mb) for i, f in a.items()}
    out |= {i: f + ma for i, f in b.items() if i not in a}
    return dict(sorted(out.items(), key=lambda x: (-x[1], x[0]))[:k])


def arrays(cells):
    cols = np.zeros((4, len(cells)))
    for j, c in enumerate(cells):
        for s, (i, f) in enumerate(sorted(c.items(), key=lambda x: (-x[1], x[0]))):
            cols[2 * s, j], cols[2 * s + 1, j] = i, f
    return cols[0].astype(int), cols[1], cols[2].astype(int), cols[3]


def back(cols):
    return [{int(i): f for i, f in ((a, b), (c, d)) if f > 0} for a, b, c, d in zip(*cols)]


CASES = [
    ({}, {}), ({1: 3}, {}), ({1: 3}, {1: 2}), ({1: 3}, {2: 2}), ({1: 5, 2: 3}, {2: 4}), ({1: 5, 2: 3}, {3: 4}), ({1: 5, 2: 3}, {1: 2, 2: 6}),
    ({1: 5, 2: 3}, {3: 4, 2: 2}), ({1: 5, 2: 3}, {1: 4, 3: 2}), ({1: 5, 2: 3}, {2: 4, 3: 2}), ({1: 5, 2: 3}, {3: 4, 4: 2}), ({1: 2, 2: 2}, {3: 2, 4: 2}),
]


@pytest.mark.parametrize("a,b", CASES)
def test_merge_keeps_mass(a, b):
    got = back(merge_cells(arrays([a]), arrays([b])))[0]
    assert got == plain_merge(a, b)
    assert sum(got.values()) == sum(a.values()) + sum(b.values())


def random_cell(rng):
    return {i: float(2 ** rng.randrange(5)) for i in rng.sample(range(1, 7), rng.randrange(3))}


def test_kernel_equals_definition_and_commutes():
    rng = random.Random(4)
    a, b = [random_cell(rng) for _ in range(3000)], [random_cell(rng) for _ in range(3000)]
    got = back(merge_cells(arrays(a), arrays(b)))
    assert got == [plain_merge(x, y) for x, y in zip(a, b)]
    assert got == back(merge_cells(arrays(b), arrays(a)))


def test_column_form_equals_definition(spark):
    rng = random.Random(5)
    pairs = [(random_cell(rng), random_cell(rng)) for _ in range(300)] + CASES
    pack = lambda c: sorted([(-float(f), i) for i, f in c.items()])
    df = spark.createDataFrame([(k, pack(a), pack(b)) for k, (a, b) in enumerate(pairs)], f"k int, a {cell.TYPE}, b {cell.TYPE}")
    rows = df.select("k", cell.merge(F.col("a"), F.col("b")).alias("m"), cell.merge(F.col("a"), F.col("b"), 3).alias("m3")).collect()
    for r in rows:
        a, b = pairs[r.k]
        assert {c.i: -c.n for c in r.m} == plain_merge(a, b)
        assert {c.i: -c.n for c in r.m3} == plain_merge(a, b, 3)


def test_update_is_merge_with_singleton():
    c = {}
    for i, x in [(1, 2.0), (2, 1.0), (3, 1.0), (1, 1.0), (3, 4.0)]:
        c = plain_merge(c, {i: x})
    assert c == {3: 6.0, 1: 3.0}


@pytest.mark.parametrize("combine", [True, False])
def test_sketch_invariants_on_random_streams(combine):
    rng = np.random.default_rng(1)
    items = (rng.zipf(1.3, 4000) % 500).astype(np.int64)
    weights = 2.0 ** rng.integers(0, 6, 4000)
    p = SketchParams(d=3, w=16)
    s = NumpySketch(p)
    for lo in range(0, 4000, 700):
        s.update(items[lo : lo + 700], weights[lo : lo + 700], combine)
    mass = np.zeros(48)
    at = p.hashes.arrays(items)
    exact = np.bincount(items, weights, 500)
    for r in range(3):
        mass[r * 16 : r * 16 + 16] = np.bincount(at[r], weights, 16)
    i1, f1, i2, f2 = s.cells
    assert np.array_equal(f1 + f2, mass) and s.count == weights.sum()
    assert (f2 <= mass / 2).all()
    for i, f in ((i1, f1), (i2, f2)):
        on = f > 0
        assert (f[on] >= exact[i[on]]).all() and (f[on] - f2[on] <= exact[i[on]]).all()


def test_reduce_by_key_is_one_cell_per_key():
    rng = np.random.default_rng(2)
    key = rng.integers(0, 40, 1000)
    none = np.zeros(1000, np.int64)
    k, cells = reduce_by_key(key, (rng.integers(1, 9, 1000), np.ones(1000), none, none.astype(float)))
    assert sorted(k.tolist()) == sorted(set(key.tolist()))
    assert (cells[1] + cells[3]).sum() == 1000


def test_unfloored_half_bound_on_fractional_weights():
    c = plain_merge({1: 0.75}, {2: 0.75})
    assert min(c.values()) <= sum(c.values()) / 2 and min(c.values()) > int(sum(c.values()) / 2)


def test_sizing():
    assert dimension(0.001, 0.02) == (4, 1360)
    assert dimension(0.001, 0.02, "countmin")[1] == 2719
    assert abs(implied(4, 1340)[0] - 0.001014) < 1e-6
    assert abs(miss_bound(0.01, 4, 1340) - 1.94e-6) < 1e-8
    with pytest.raises(ValueError):
        SketchParams(w=1340).check_support(0.001)
    assert SketchParams(w=1340).check_support(0.001, strict=False) is False
    with pytest.raises(ValueError):
        dimension(0, 0.5)


def test_only_two_counters_keep_the_norm(spark):
    from fadedhh.operators.invariants import summary_deficit

    rng = random.Random(9)
    lost = {}
    for k in (2, 3, 8):
        def summary():
            c = {}
            for _ in range(40):
                c = plain_merge(c, {rng.randrange(30): float(rng.randrange(1, 5))}, k)
            return sorted((-f, i) for i, f in c.items())

        df = spark.createDataFrame([(summary(), summary()) for _ in range(60)], f"a {cell.TYPE}, b {cell.TYPE}")
        lost[k] = [r.deficit for r in summary_deficit(df, k).collect()]
    assert set(lost[2]) == {0.0} and min(lost[3]) >= 0 and min(lost[8]) >= 0 and max(lost[3]) > 0


def test_merge_is_not_associative_but_keeps_mass():
    rng = random.Random(11)
    differ = 0
    for _ in range(400):
        a, b, c = (random_cell(rng) for _ in range(3))
        x, y = plain_merge(plain_merge(a, b), c), plain_merge(a, plain_merge(b, c))
        assert sum(x.values()) == sum(y.values()) == sum(map(lambda s: sum(s.values()), (a, b, c)))
        differ += x != y
    assert differ
