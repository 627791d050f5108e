"""Regions longer than any fixed number of rounds."""

from cloudlattice.operators import cells


def test_long_region_is_one(spark):
    grid = spark.createDataFrame([(k, 0, 0, 5) for k in range(70)] + [(80, 0, 0, 5)], "i long, j long, k long, n long").coalesce(1)
    got = cells.dense_regions(grid, 1).groupBy("region").count().collect()
    assert sorted(r["count"] for r in got) == [1, 70]
