"""Ranks from the compared codecs alone, keys once for all strides, and numbers in few bytes."""

import duckdb
import numpy as np
import pytest

from cloudlattice.operators import sequences
from cloudlattice.operators.families import Bound
from cloudlattice.plans import catalogue, rates
from cloudlattice.sources import clouds


@pytest.fixture
def fresh(monkeypatch):
    monkeypatch.setattr(sequences, "RANGE", 700)  # up to nine ranges a sequence
    monkeypatch.setattr(rates, "_known", {})


@pytest.mark.parametrize("name", ["friedman_ranks", "friedman_statistic", "nemenyi_cliques"])
def test_ranks_size_only_compared_codecs_and_equal_sql(spark, sf_dir, fresh, name):
    con = duckdb.connect()
    for t in ("lineitem", "events", "orders", "embeddings", "documents", "part", "customer"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    df = catalogue.QUERIES[name](spark, sf_dir)
    columns = sorted(df.columns)
    assert sorted(map(repr, map(tuple, df.select(*columns).collect()))) == sorted(map(repr, con.sql(f"SELECT {', '.join(columns)} FROM ({catalogue.ORACLES[name]})").fetchall()))
    assert {row[2] for rows in rates._known.values() for row in rows} == set(rates.RANKED)


@pytest.mark.parametrize("name", ["ratios_under_targets", "pareto_front"])
def test_whole_table_has_every_codec(spark, sf_dir, fresh, name):
    con = duckdb.connect()
    for t in ("lineitem", "events", "orders", "embeddings", "documents", "part", "customer"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    df = catalogue.QUERIES[name](spark, sf_dir)
    columns = sorted(df.columns)
    assert sorted(map(repr, map(tuple, df.select(*columns).collect()))) == sorted(map(repr, con.sql(f"SELECT {', '.join(columns)} FROM ({catalogue.ORACLES[name]})").fetchall()))
    assert len({row[2] for rows in rates._known.values() for row in rows}) == 10


def test_strides_share_keys(spark, monkeypatch):
    calls = []
    monkeypatch.setattr(sequences, "quantized", lambda kinds, bound, p, errors=None, f=sequences.quantized: calls.append(p.shape[1]) or f(kinds, bound, p, errors))
    plan = sequences.Plan([(0, Bound.of(1e-3), k) for k in (4, 2, 1)], [[(0.0, 1.0)] * 3], [1], ("to_morton",))
    rng = np.random.default_rng(1)
    points = rng.random((3, 1000))

    class Points:  # takes the place of a table, so that the task runs here
        def select(self, *names):
            return self

        def mapInArrow(self, task, schema):
            import pyarrow as pa

            columns = [pa.array(np.zeros(1000, np.int32)), *map(pa.array, points), pa.array(np.arange(1000))]
            return list(task(iter([pa.RecordBatch.from_arrays(columns, ["cloud", "x", "y", "z", "number"])])))

    (got,) = sequences.from_points(Points(), plan)
    assert calls == [1000]
    for seq, v, c in zip(*(got.column(n).to_pylist() for n in ("seq", "v", "c")), strict=True):
        stride = plan.seqs[seq][2]
        keys, counts = sequences.counted(sequences.quantized(("to_morton",), Bound.of(1e-3), points[:, ::stride])["bcc"])
        assert sequences.unpacked(v, True).tolist() == keys.tolist()
        assert (sequences.unpacked(c).tolist() if c else None) == (None if counts is None else counts.tolist())


def test_numbers_in_few_bytes():
    for a in ([], [0], [7, 9, 300], [1 << 50, (1 << 50) + 1], [0, 5, 1 << 40], [3] * 4):
        held = sequences.packed(np.array(a, np.int64), True)
        assert (sequences.unpacked(held, True).tolist() if held else []) == a
        held = sequences.packed(np.array(a, np.int64))
        assert (sequences.unpacked(held).tolist() if held else []) == a
    assert len(sequences.packed(np.arange(1 << 50, (1 << 50) + 1000), True)) < 1100


def test_census_is_that_of_the_clouds(spark, sf_dir):
    got = {r["cloud"]: r for r in clouds.census(spark, sf_dir, rates.NAMES).collect()}
    for k, name in enumerate(rates.NAMES):
        cloud = clouds.load(spark, sf_dir, name)
        assert got[k]["n"] == cloud.count()
        assert {e: got[k][e] for e in ("x_lo", "x_hi", "y_lo", "y_hi", "z_lo", "z_hi")} == clouds.bounding_box(cloud)


@pytest.mark.parametrize("levels, most", [(1, 1), (3, 1), (4, 2), (6, 9), (12, 1), (16, 2)])
def test_tree_nodes_from_gaps_are_those_of_every_level(levels, most):
    rng = np.random.default_rng(levels)
    keys = np.unique(rng.integers(0, 1 << min(3 * levels, 11), 300))
    counts = rng.integers(1, most + 1, len(keys))
    want = 0
    for shift in range(1, 3 * levels + 1):
        n = np.bincount(np.unique(keys >> shift, return_inverse=True)[1], counts)
        want += sum(int(x).bit_length() for x in n[1:])
    assert sequences.within(keys, counts, 3 * levels) == want


def test_counts_of_zero_stay():
    keys, counts = sequences.counted(np.array([2, 1, 2, 3]), np.array([0, 1, 1, 0]))
    assert keys.tolist() == [1, 2, 3] and counts.tolist() == [1, 1, 0]
