"""Sharding: longest-processing-time scheduling of groups that must stay together.

Groups (equal texts) are sized by one aggregation. Every group larger than
``total / (shards * units)`` goes through the heap on its own; at most
``shards * units`` groups can be that large. The rest are united by hash into
``shards * units`` bundles, and a bundle goes through the heap as one item. So the
driver holds at most ``2 * shards * units`` items whatever the size of the corpus,
equal texts always share a shard, and shard sizes differ by at most the items
placed last. Whether a group enters the heap alone depends on its share of all
bytes only; where no group is that small, this is the plain rule.

Slots are numbered without sorting a whole shard in one task: rows fall into cells
of a shard by a hash, cells are counted, and a slot is the cell's start plus the
row's number within the cell.
"""

from __future__ import annotations

import heapq

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cloudlattice.llm.work import load, utf8_bytes, written

SHARDS = 40
UNITS = 256
ROW_BYTES = 16
ROWS_PER_CELL = 50_000


def lpt(sizes: list[tuple[str, int]], shards: int) -> dict[str, int]:
    """Items by falling size (ties by name), each to the least-loaded shard (ties to the lowest)."""
    loads = [(0, s) for s in range(shards)]
    placed = {}
    for name, size in sorted(sizes, key=lambda x: (-x[1], x[0])):
        load_, shard = heapq.heappop(loads)
        placed[name] = shard
        heapq.heappush(loads, (load_ + size, shard))
    return placed


def group_key(text: Column) -> Column:
    """Two 64-bit hashes of the text; null and empty texts are one group."""
    text = F.coalesce(text, F.lit(""))
    return F.concat_ws(":", F.hex(F.xxhash64(text)), F.hex(F.xxhash64(F.lit(1), text)))


def bundle_key(group: Column, bundles: int) -> Column:
    return F.concat(F.lit("b"), F.pmod(F.xxhash64(F.lit(2), group), F.lit(bundles)).cast("string"))


def shard_documents(docs: DataFrame, shards: int = SHARDS, units: int = UNITS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: id, size, text_crc32, shard, slot.

    Size: UTF-8 bytes plus 16; null texts count no bytes and share a group with empty
    ones. Repeated rows each get a slot; an empty table gives an empty result; other
    columns of the input are ignored. Long texts are only hashed.
    """
    spark = docs.sparkSession
    rows = docs.select(F.col(id_col).alias("doc_id"), utf8_bytes(F.col(text_col)).alias("bytes"), F.coalesce(F.crc32(F.col(text_col)), F.lit(0)).cast("long").alias("text_crc32"), group_key(F.col(text_col)).alias("g")).withColumn("size", F.col("bytes") + ROW_BYTES)
    # kept in the table, so that repeated rows spread over cells in the same way whenever it is read
    rows = written(rows.drop("bytes").withColumn("salt", F.pmod(F.monotonically_increasing_id(), F.lit(1024))), "shard-rows")
    groups = written(rows.groupBy("g").agg(F.sum("size").alias("size"), F.count(F.lit(1)).alias("n")), "shard-groups")
    total, count = groups.agg(F.coalesce(F.sum("size"), F.lit(0)), F.coalesce(F.sum("n"), F.lit(0))).first()
    bundles = shards * units
    alone = F.col("size") * bundles > F.lit(total)
    item = F.when(alone, F.col("g")).otherwise(bundle_key(F.col("g"), bundles))
    # at most `bundles` groups exceed a share of 1/bundles, and there are as many bundles
    items = [(r[0], r[1]) for r in groups.groupBy(item.alias("item")).agg(F.sum("size").alias("size")).collect()]
    placed = spark.createDataFrame(list(lpt(items, shards).items()), "item string, shard int")
    alone_keys = F.broadcast(placed.where(~F.col("item").startswith("b")).select(F.col("item").alias("g"), F.col("shard").alias("own")))
    bundle_shards = F.broadcast(placed.where(F.col("item").startswith("b")).select(F.col("item").alias("bundle"), F.col("shard").alias("shared")))
    placed_rows = (
        rows.join(alone_keys, "g", "left")
        .withColumn("bundle", F.when(F.col("own").isNull(), bundle_key(F.col("g"), bundles)))
        .join(bundle_shards, "bundle", "left")
        .select("doc_id", "size", "text_crc32", "salt", F.coalesce("own", "shared").alias("shard"))
    )
    return numbered(placed_rows, max(1, -(-count // (shards * ROWS_PER_CELL))) * 8)


def numbered(rows: DataFrame, cells: int) -> DataFrame:
    """Gapless slots in each shard: cell starts from counts, then a row number inside each cell."""
    rows = rows.withColumn("cell", F.pmod(F.xxhash64(F.lit(3), "doc_id", "text_crc32", "salt"), F.lit(cells)))
    before = Window.partitionBy("shard").orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)
    starts = rows.groupBy("shard", "cell").agg(F.count(F.lit(1)).alias("n")).select("shard", "cell", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("start"))
    inside = Window.partitionBy("shard", "cell").orderBy("doc_id", "text_crc32")
    return (
        rows.withColumn("at", F.row_number().over(inside) - 1)
        .join(starts, ["shard", "cell"])
        .select("doc_id", "size", "text_crc32", "shard", (F.col("start") + F.col("at")).cast("long").alias("slot"))
    )


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    placed = shard_documents(load(spark, sf_dir, "documents"))
    return placed.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
