"""Mixing sources to target weights with a multivariate-hypergeometric splitting tree.

Each source's documents fall into ``blocks`` disjoint blocks by a seeded hash, which
is a random permutation of the source cut into blocks. A source's target in words
is met by whole epochs of all blocks, then whole blocks in permuted order, then one
block cut at a word. The block draws of all sources form exact quotas, which a
binary tree deals to the output shards: a node's quotas are split by a
multivariate hypergeometric draw, so every shard gets a random sample of the whole
mix with exact totals. Within a shard rows are ordered by a seeded hash.

The driver plans over one number per block. A source has a block for about
``BLOCK_ROWS`` of its rows, a power of two up to ``MOST_BLOCKS``; there may be at most
``MOST_PLANNED`` blocks and ``MOST_SOURCES`` sources, so the plan is bounded; documents only meet DataFrame operations.
There is a shard for about ``SHARD_WORDS`` words of the mix, ``SHARDS`` of them at least
and ``MOST_SHARDS`` at most.
"""

from __future__ import annotations

import random
from collections import Counter
from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cloudlattice.llm.work import load, word_count

SHARDS, MOST_SHARDS, SHARD_WORDS = 16, 4096, 1 << 24
BLOCK_ROWS, MOST_BLOCKS, MOST_PLANNED, MOST_SOURCES = 64, 4096, 1 << 20, 1 << 16
MOST = 3.0
WEIGHTS = (1.0, 2.0, 3.0)
SEED = 17
ADDED = ("size", "source_size", "target", "draws")


def capped_targets(sizes: Sequence[float], weights: Sequence[float], total: float, most: float = MOST) -> list[float]:
    """Shares of ``total`` by weight, none above ``most`` times its size; the excess is reshared by weight."""
    targets, open_ = [0.0] * len(sizes), [i for i, s in enumerate(sizes) if s > 0]
    left = float(total)
    while open_:
        weight = sum(weights[i] for i in open_)
        full = [i for i in open_ if left * weights[i] / weight > most * sizes[i]]
        if not full:
            for i in open_:
                targets[i] = left * weights[i] / weight
            break
        for i in full:
            targets[i] = most * sizes[i]
        left -= sum(targets[i] for i in full)
        open_ = [i for i in open_ if i not in set(full)]
    return targets


def split_quotas(quotas: dict[int, int], shards: int, rng: random.Random) -> list[dict[int, int]]:
    """Deal quotas (draws by source) to shards by recursive halving.

    A node with ``shards`` leaves gives its left child the share of draws that its
    leaves stand for, and which draws they are is a multivariate hypergeometric
    sample. Item ``s`` of the result holds shard ``s``'s quotas; they sum exactly.
    """
    if shards == 1:
        return [quotas]
    half, n = shards // 2, sum(quotas.values())
    left = Counter(rng.sample(list(quotas), counts=quotas.values(), k=n * half // shards)) if n else Counter()
    right = {i: q - left[i] for i, q in quotas.items() if q > left[i]}
    return split_quotas({i: left[i] for i in quotas if left[i]}, half, rng) + split_quotas(right, shards - half, rng)


def plan(blocks: Sequence[Sequence[int]], targets: Sequence[float], shards: int, seed: int) -> list[tuple]:
    """Rows (source number, block, epoch, words, shard) for every draw; ``blocks`` holds the words of each source's blocks."""
    draws: list[list[tuple[int, int, int]]] = []
    for k, own in enumerate(blocks):
        left, mine = round(targets[k]), []
        order = sorted((b for b in range(len(own)) if own[b]), key=lambda b: random.Random(f"{seed}:{k}:{b}").random())
        epoch = 0
        while left > 0 and order:
            for b in order:
                take = min(left, own[b])
                if not take:
                    break
                mine.append((b, epoch, take))
                left -= take
            epoch += 1
        draws.append(mine)
    rng = random.Random(seed)
    dealt = split_quotas({k: len(d) for k, d in enumerate(draws) if d}, shards, rng)
    for mine in draws:
        rng.shuffle(mine)
    at = [0] * len(draws)
    rows = []
    for shard, quotas in enumerate(dealt):
        for k, quota in quotas.items():
            rows.extend((k, b, epoch, take, shard) for b, epoch, take in draws[k][at[k] : at[k] + quota])
            at[k] += quota
    return rows


def block_count(rows: int, sources: int) -> int:
    """Blocks of a source, a power of two; those of all sources together are at most ``MOST_PLANNED``."""
    most = min(MOST_BLOCKS, 1 << (MOST_PLANNED // sources).bit_length() - 1)
    return min(most, 1 << max(3, (rows // BLOCK_ROWS).bit_length()))


def mix_documents(docs: DataFrame, weights: Sequence[float] = WEIGHTS, shards: int | None = None, seed: int = SEED) -> DataFrame:
    """Every document with the draws that take words from it.

    Result: the input's columns plus size, source_size, target and ``draws``, an array
    of (epoch, shard, words, place) by epoch; place is the seeded key that orders rows inside
    a shard. Input columns of these names are replaced. Null texts have size 0 and nothing is drawn from them; a null source is a
    source of its own, the last; repeated rows are drawn on their own; an empty table
    gives an empty result. Names of the input that start with ``_mix_`` are not allowed.
    Over ``MOST_SOURCES`` sources are an error.
    """
    spark = docs.sparkSession
    kept = [c for c in docs.columns if c not in ADDED]
    docs = docs.select(*kept)
    counts = {r[0]: r[1] for r in docs.groupBy("source").count().limit(MOST_SOURCES + 1).collect()}
    if len(counts) > MOST_SOURCES:
        raise ValueError(f"over {MOST_SOURCES} sources")
    order = sorted(counts, key=lambda s: (s is None, (s or "").encode("utf-32-be")))
    parts = [block_count(counts[s], len(order)) for s in order]
    numbers = spark.createDataFrame([(s, k, parts[k]) for k, s in enumerate(order)], "_mix_s string, _mix_k int, _mix_parts int")
    rows = docs.withColumn("_mix_size", word_count(F.col("text"))).withColumn("_mix_text", F.xxhash64("text"))
    rows = rows.join(numbers, F.col("source").eqNullSafe(F.col("_mix_s"))).drop("_mix_s")
    rows = rows.withColumn("_mix_block", F.pmod(F.xxhash64(F.lit(seed), "doc_id", "_mix_text"), F.col("_mix_parts")).cast("int"))
    blocks = [[0] * n for n in parts]
    for k, block, words in rows.groupBy("_mix_k", "_mix_block").agg(F.sum("_mix_size")).collect():  # a number for each block
        blocks[k][block] = words
    sizes = [sum(b) for b in blocks]
    targets = capped_targets(sizes, [weights[k % len(weights)] for k in range(len(sizes))], sum(sizes))
    shards = shards or max(SHARDS, min(MOST_SHARDS, sum(sizes) // SHARD_WORDS))
    planned = spark.createDataFrame(plan(blocks, targets, shards, seed), "_mix_k int, _mix_block int, epoch int, take long, shard int")
    drawn = planned.groupBy("_mix_k", "_mix_block").agg(F.sort_array(F.collect_list(F.struct("epoch", "shard", "take"))).alias("_mix_takes"))
    totals = spark.createDataFrame(list(zip(range(len(sizes)), sizes, targets, strict=True)), "_mix_k int, source_size long, target double")
    inside = Window.partitionBy("_mix_k", "_mix_block").orderBy(F.xxhash64(F.lit(seed + 1), "doc_id", "_mix_text"), "doc_id").rowsBetween(Window.unboundedPreceding, -1)
    laid = rows.withColumn("_mix_from", F.coalesce(F.sum("_mix_size").over(inside), F.lit(0)))
    words = lambda x: F.greatest(F.lit(0).cast("long"), F.least(F.col("_mix_size"), x["take"] - F.col("_mix_from")))
    draws = F.filter(
        F.transform(F.coalesce(F.col("_mix_takes"), F.array()), lambda x: F.struct(x["epoch"].alias("epoch"), x["shard"].alias("shard"), words(x).alias("words"), F.xxhash64(F.lit(seed + 2), "doc_id", "_mix_text", x["epoch"]).alias("place"))),
        lambda x: x["words"] > 0,
    )
    return laid.join(drawn, ["_mix_k", "_mix_block"], "left").join(totals, "_mix_k", "left").select(*kept, F.col("_mix_size").alias("size"), "source_size", "target", draws.alias("draws"))


def mixed(docs: DataFrame, **options) -> DataFrame:
    """The mix as documents: a row for each epoch that takes at least half of a document's words.

    Repeats have the document's columns unchanged. All rows of an output shard are in
    one partition, shuffled by the seeded place; a partition may hold several shards, one after another.
    """
    held = {c: f"_held_{c}" for c in ADDED if c in docs.columns}
    got = mix_documents(docs.withColumnsRenamed(held), **options)
    repeats = got.withColumn("_mix_draw", F.explode("draws")).where(F.col("_mix_draw.words") * 2 >= F.col("size"))
    placed = repeats.repartition(F.col("_mix_draw.shard"))
    return placed.sortWithinPartitions(F.col("_mix_draw.shard"), F.col("_mix_draw.place"), "doc_id").select(*[F.col(held.get(c, c)).alias(c) for c in docs.columns])


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, size, source_size, target, taken, and for each draw by epoch its shard, the words that it takes and its place there."""
    got = mix_documents(load(spark, sf_dir, "documents").select("doc_id", "source", "text"))
    taken = F.aggregate("draws", F.lit(0).cast("long"), lambda s, x: s + x["words"])
    each = lambda name: F.transform("draws", lambda x: x[name])
    return got.select("doc_id", "size", "source_size", "target", taken.alias("taken"), each("shard").alias("shards"), each("words").alias("drawn"), each("place").alias("places"))
