"""Codec sizes from key ranges: many ranges a sequence, and the same results as the SQL."""

import duckdb
import numpy as np
import pytest

from cloudlattice.functions import curves
from cloudlattice.operators import sequences
from cloudlattice.plans import catalogue, rates


def test_hilbert_keys_of_several_levels_at_once():
    rng = np.random.default_rng(3)
    for bits in (1, 3, 4, 7, 15):
        cell = [rng.integers(0, 1 << bits, 500) for _ in range(3)]
        assert (sequences.hilbert(sequences.morton(cell), bits) == curves.hilbert_numpy(*cell, bits)).all()


def test_counted_merges_parts():
    keys, counts = sequences.counted(np.array([5, 1, 5, 9]), np.array([2, 1, 3, 1]))
    assert keys.tolist() == [1, 5, 9] and counts.tolist() == [1, 5, 1]
    assert sequences.counted(np.array([3, 2]))[1] is None and len(sequences.counted(np.zeros(0, np.int64), np.zeros(0, np.int64))[0]) == 0


def test_bad_coordinates_are_an_error():
    with pytest.raises(ValueError, match="not finite"):
        sequences.unit(np.array([[0.0, np.nan]] * 3), [(0.0, 1.0)] * 3)


@pytest.mark.parametrize("name", ["rate_distortion", "fixed_ratio", "curve_gap", "stride_ratios"])
def test_many_ranges_equal_sql(spark, sf_dir, monkeypatch, name):
    monkeypatch.setattr(sequences, "RANGE", 700)  # up to nine ranges a sequence
    monkeypatch.setattr(rates, "_known", {})
    con = duckdb.connect()
    for t in ("lineitem", "events", "orders", "embeddings", "documents", "part", "customer"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    df = catalogue.QUERIES[name](spark, sf_dir)
    columns = sorted(df.columns)
    assert sorted(map(repr, map(tuple, df.select(*columns).collect()))) == sorted(map(repr, con.sql(f"SELECT {', '.join(columns)} FROM ({catalogue.ORACLES[name]})").fetchall()))
