"""What bounds share is done once: grid keys are sent for the finest one, and digits of the block transform serve all."""

import numpy as np
import pyarrow as pa
import pytest

from cloudlattice.operators import sequences
from cloudlattice.operators.families import Bound

BOUNDS = [Bound.of(eb) for eb in (2e-2, 5e-3, 1e-3)]


def plan_of(kinds, parts=1):
    return sequences.Plan([(0, bound, 1) for bound in BOUNDS], [[(0.0, 1.0)] * 3], [parts], kinds, [80])


@pytest.mark.parametrize("parts", [1, 4])
@pytest.mark.parametrize("spread", [1.0, 0.01])
def test_trees_of_all_bounds_from_the_finest_grid(parts, spread):
    rng = np.random.default_rng(5)
    p = np.concatenate([rng.random((3, 700)) * spread, rng.random((3, 40)), np.ones((3, 2))], 1)
    plan = sequences.with_splitters(plan_of(("grid", "octree_occupancy"), parts), {0: p})
    facts, pairs = [], {k: {} for k in range(3)}
    ranged = {}
    for row in sequences.in_order(plan, 0, p, p):
        if sequences.KINDS[row[1]] == "grid":
            assert row[0] == 2  # the finest, once for all
            ranged.setdefault(row[3], []).append(row)
    assert len(ranged) == parts
    for rows in ranged.values():
        for row in sequences.merge(plan, sequences.table(rows)):
            if row[2] == sequences.FACTS:
                facts.append(type("Row", (), dict(zip(("seq", "kind", "stream", "bucket", "v", "c"), row, strict=True))))
            else:
                for v, c in zip(sequences.unpacked(row[4], True), sequences.unpacked(row[5]), strict=True):
                    pairs[row[0]][int(v)] = pairs[row[0]].get(int(v), 0) + int(c)
    extra, tree, _ = sequences.boundaries(plan, facts)
    for k, bound in enumerate(BOUNDS):
        levels = bound.levels
        keys = sequences.morton(sequences.grid(p, levels))
        inner = sum(int(n).bit_length() for shift in range(1, 3 * levels + 1) for n in np.unique(keys >> shift, return_counts=True)[1])
        leaves = sum(2 * int(n).bit_length() - 1 for n in np.unique(keys, return_counts=True)[1])
        assert tree[k] == [leaves, inner]
        masks, want = {}, {}
        for level in range(1, levels + 1):
            for child in np.unique(keys >> 3 * (levels - level)).tolist():
                masks[level, child >> 3] = masks.get((level, child >> 3), 0) | 1 << (child & 7)
        for (level, node), mask in masks.items():
            pair = masks.get((level - 1, node >> 3), 0) * 256 + mask
            want[pair] = want.get(pair, 0) + 1
        for pair in extra[k, sequences.KINDS.index("grid"), 0, 0]:
            pairs[k][pair] = pairs[k].get(pair, 0) + 1
        assert pairs[k] == want


def test_digits_of_the_transform_serve_all_bounds():
    p = np.random.default_rng(1).random((3, 1003))
    together = sequences.transformed(p, BOUNDS)
    assert together == [sequences.transformed(p, [bound])[0] for bound in BOUNDS]
    assert [worst <= (4 * bound.eb) ** 2 for (_, _, worst), bound in zip(together, BOUNDS, strict=True)] == [True] * 3
    assert together[0][0] < together[1][0] < together[2][0]


def test_dense_values_are_counted_as_others_are():
    for a in (np.array([3, 0, 3, 1]), np.array([2, 0, 1]), np.array([-1, 0, -1]), np.array([1 << 40, 5, 5])):
        keys, counts = sequences.counted(a)
        want, n = np.unique(a, return_counts=True)
        assert keys.tolist() == want.tolist() and (counts is None) == (n.max() == 1) and (counts is None or counts.tolist() == n.tolist())


def test_points_of_a_slice_are_put_in_order(spark, monkeypatch):
    plan = plan_of(("array_predictive", "sums"))
    rng = np.random.default_rng(2)
    n = 500
    p, pid = rng.random((3, n)), rng.permutation(n).astype(np.int64)
    columns = {"cloud": np.zeros(n, np.int32), "slice": np.zeros(n, np.int64), "pid": pid, "x": p[0], "y": p[1], "z": p[2]}
    got = sequences.measured(sequences.from_slices(spark.createDataFrame(pa.table(columns)), plan, 2), plan, 2)
    at = p[:, np.argsort(pid)]
    for found, bound in zip(got, BOUNDS, strict=True):
        gaps = [np.diff(np.floor(a / bound.step + 0.5).astype(np.int64), prepend=0) for a in at]
        want = 0.0
        for gap in gaps:
            v, c = np.unique(gap << 1 ^ gap >> 63, return_counts=True)
            entropy = float(n * np.log2(n) - (c * np.log2(c)).sum() + sum(int(x).bit_length() + sequences.SYMBOL_BITS for x in v))
            order = lambda k: float(sum(((int(x) >> k) + 1).bit_length() * 2 - 1 + k for x in gap << 1 ^ gap >> 63))
            want += min(entropy, *(order(k) for k in sequences.ORDERS))
        assert found["bits"]["array_predictive"] == pytest.approx(want)


def test_points_without_an_id_are_a_slice(spark):
    plan = plan_of(("array_predictive", "sums"))
    p = np.full((3, 6), 0.25)
    pid = pa.array([7, None, 3, None, 5, None], pa.int64())
    of = pa.array([0, None, 0, None, 0, None], pa.int64())
    points = spark.createDataFrame(pa.table({"cloud": pa.array([0] * 6, pa.int32()), "slice": of, "pid": pid, "x": p[0], "y": p[1], "z": p[2]}))
    rows = [r for r in sequences.from_slices(points, plan, 2).collect() if r.seq == 0 and sequences.KINDS[r.kind] == "sums"]
    assert sorted(np.frombuffer(r.v)[0] for r in rows) == [3, 3]
