"""Null ids and clashing column names: no stage drops or mixes up such rows."""

import pytest
from pyspark.sql import functions as F

from cloudlattice.llm import grid_join, mixing, packing, sharding, shingle_join, suffix_dedup

COLUMNS = "doc_id long, text string, lang string, source string, n_chars long, size string, draws string, ranges string, text_hash string, root string"


@pytest.fixture(scope="module")
def odd(spark):
    long = " ".join(f"w{k}" for k in range(300))
    rows = [(1, long), (2, long), (None, long), (None, None), (3, ""), (4, "a b c d e f g"), (4, "other words than before here")]
    return spark.createDataFrame([(i, t, None, None, None, "x", "y", "z", "h", "r") for i, t in rows], COLUMNS)


def test_stages_keep_columns_and_rows_without_ids(odd):
    kept = shingle_join.representatives(odd, 80, 5)
    assert kept.columns == odd.columns
    assert kept.where("doc_id is null").count() == 2 and kept.where("doc_id in (1, 2)").count() == 1 and kept.where("doc_id = 4").count() == 2
    left = suffix_dedup.deduplicated(odd)
    assert left.columns == odd.columns and left.count() == 7
    assert {r["text"] for r in left.where("doc_id in (1, 2)").collect()} == {""} and left.where("ranges = 'z'").count() == 7
    mixed = mixing.mixed(odd)
    assert mixed.columns == odd.columns and set(mixed.select("size", "draws").distinct().collect()) == {("x", "y")}


def test_other_operators_take_null_ids(odd, spark):
    assert sharding.shard_documents(odd, 3).count() == 7
    assert packing.pack_documents(odd, packing.default_tokenizer()).select(F.sum("length")).first()[0] > 7
    table = spark.createDataFrame([(None, [1.0, 0.0], 1), (5, [1.0, 0.0], 1), (6, [1.0, 0.01], 1)], "vec_id long, embedding array<float>, label int")
    got = {r["vec_id"]: r for r in grid_join.near_duplicates(table).collect()}
    assert got[5]["n_links"] == 1 and got[6]["component_id"] == 5 and got[None]["n_links"] == 0
