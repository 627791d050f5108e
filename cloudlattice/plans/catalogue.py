"""Every query of the library, with the SQL that checks it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cloudlattice.plans import choices, codecs, geometry, ordering, rates, regions, statistics, workloads
from cloudlattice.plans.workloads import flagship
from cloudlattice.streaming import cells as stream

__all__ = ["QUERIES", "ORACLES", "flagship"]

STEPS = (3600.0, 10.0, 25.0)


def stream_cell_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cells of each day of events, by the plan that streams run too."""
    events = spark.read.parquet(f"{sf_dir}/events.parquet").select("ts", "user_id", "value")
    return stream.windowed_counts(events, STEPS, F.window("ts", "1 day")).select(F.date_format("start", "yyyy-MM-dd").alias("day"), "i", "j", "k", "n")


def _stream_sql() -> str:
    at = "SELECT strftime(ts, '%Y-%m-%d') AS day, (hour(ts) * 3600 + minute(ts) * 60 + floor(second(ts)))::DOUBLE / 3600.0::DOUBLE AS u, user_id::DOUBLE / 10.0::DOUBLE AS v, value / 25.0::DOUBLE AS w FROM events"
    from cloudlattice.plans import duck

    return f"SELECT day, i + {stream.SHIFT} AS i, j + {stream.SHIFT} AS j, k + {stream.SHIFT} AS k, count(*) AS n FROM ({duck.celled(at)}) GROUP BY ALL"


_modules = (geometry, ordering, regions, codecs, statistics, rates, choices, workloads)
QUERIES = {name: f for m in _modules for name, f in m.QUERIES.items()} | {"stream_cell_counts": stream_cell_counts}
ORACLES = {name: sql for m in _modules for name, sql in m.ORACLES.items()} | {"stream_cell_counts": _stream_sql()}
