"""Mixing sources to target weights with a multivariate-hypergeometric splitting tree.

Each source is dealt into permuted blocks, more the larger it is. How many words a source gives is
fixed by weights and a ceiling; which of its blocks are drawn follows from the
permutation, so draws are disjoint. The counts of drawn blocks are split down
a binary tree over the output shards: at each node the left half receives a
multivariate-hypergeometric share of every source. In a shard, rows follow a
seeded order.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from corpusmap.llm.common import documents, fresh_names, materialize, row_key, text_or_empty, word_count

BLOCK_WORDS, LEAST_BLOCKS, MOST_BLOCKS = 1 << 16, 64, 1 << 20
BROADCAST_ROWS = 1 << 19  # of some tens of bytes
#: fixed values: weights of the sources in code-point order, repeating
WEIGHTS = (5.0, 2.0, 1.0)
MAX_SOURCES = 100_000


def water_fill(sizes: list[int], weights: list[float], total: float, ceiling: float) -> list[float]:
    """Shares of ``total`` by weight, none above ``ceiling`` times its size; the excess is shared anew by weight."""
    target, free, left = [0.0] * len(sizes), set(range(len(sizes))), float(total)
    while free:
        unit = left / sum(weights[i] for i in free)
        over = [i for i in free if weights[i] * unit > ceiling * sizes[i]]
        if not over:
            for i in free:
                target[i] = weights[i] * unit
            break
        for i in over:
            target[i] = float(ceiling * sizes[i])
            left -= target[i]
            free.discard(i)
    return target


def split_quotas(quotas: list[int], shards: int, seed: int) -> list[list[int]]:
    """Blocks of each source (columns) for each shard (rows); rows sum near-equally, columns exactly."""
    rng = np.random.default_rng(seed)
    out: list[list[int]] = []

    def node(counts: np.ndarray, n: int) -> None:
        if n == 1:
            out.append(counts.tolist())
            return
        half, all_ = n // 2, int(counts.sum())
        left = rng.multivariate_hypergeometric(counts, all_ * half // n, method="marginals")
        node(left, half)
        node(counts - left, n - half)

    node(np.array(quotas, dtype=np.int64), shards)
    return out


def draw(docs: DataFrame, size=None, share: float = 1.5, ceiling: float = 2.0, weights: tuple = WEIGHTS, shards: int = 16, seed: int = 7) -> DataFrame:
    """``docs`` plus ``mix_size, mix_source_size, mix_target, mix_shards, mix_orders``: one row per row of ``docs``.

    ``mix_shards array<int>`` holds a shard for every time the row is drawn
    (none, once or twice), ``mix_orders array<long>`` its place in the local
    shuffle of that shard; a document is drawn whole. Sources in code-point
    order take the weights in turn, null last; together they give ``share`` of
    all words, none more than ``ceiling`` times its own. Empty documents take
    part with size 0. Reruns draw the same rows; rows with equal identifier
    and text are drawn alike. An empty table gives an empty result. The names
    ``mix_...`` above are reserved; other names do no harm.

    Blocks follow the size of a source, ``BLOCK_WORDS`` words each on average.
    The texts are not shuffled: what a document's block gives is met by a
    broadcast up to ``BROADCAST_ROWS`` blocks, by a join beyond.
    """
    spark = docs.sparkSession
    size = word_count(text_or_empty("text")) if size is None else size
    key_, block_, k1, k2, n_, part_, passes_, c1, c2, shards_ = fresh_names(docs, "key", "block", "k1", "k2", "blocks", "part", "passes", "cut1", "cut2", "shards")
    c = F.col
    key = F.coalesce(F.concat(F.lit("="), c("source").cast("string")), F.lit("!"))
    keys = row_key(c("doc_id"), text_or_empty("text") if "text" in docs.columns else size.cast("string"))
    mixed = docs.withColumns({"mix_size": size.cast("long"), key_: key, k1: keys[0], k2: keys[1]})
    sized = materialize(mixed.select(c(key_).alias("key"), c("mix_size").alias("size"), c(k1).alias("k1"), c(k2).alias("k2")), "mix-sized")
    sums = sized.groupBy("key").agg(F.sum("size").alias("words")).limit(MAX_SOURCES + 1).collect()
    if len(sums) > MAX_SOURCES:
        raise ValueError("more sources than a mix has weights for")
    sums = sorted(sums, key=lambda r: (r[0] == "!", r[0].encode()))
    target = water_fill([r[1] for r in sums], [weights[i % len(weights)] for i in range(len(sums))], share * sum(r[1] for r in sums), ceiling)
    plan = []
    for r, t in zip(sums, target, strict=True):
        passes = min(int(t // r[1]), int(ceiling)) if r[1] else 0
        plan.append((r[0], int(r[1]), float(t), passes, float(t - passes * r[1]), min(MOST_BLOCKS, max(LEAST_BLOCKS, r[1] // BLOCK_WORDS))))
    plans = spark.createDataFrame(plan, "key string, source_size long, target double, passes int, rest double, blocks long")
    block_of = lambda one, two, n: F.pmod(F.xxhash64(F.lit(seed), one, two), n).cast("int")
    in_block = sized.join(F.broadcast(plans.select("key", "blocks")), "key").withColumn("block", block_of("k1", "k2", c("blocks"))).drop("blocks")  # a row per source
    blocks = materialize(in_block.groupBy("key", "block").agg(F.sum("size").alias("words")), "mix-blocks")
    inside = Window.partitionBy("key").orderBy(F.xxhash64(F.lit(seed + 1), "key", "block"), "block")  # at most MOST_BLOCKS rows
    dealt = (blocks.join(F.broadcast(plans), "key")
             .withColumn("upto", F.sum("words").over(inside))
             .withColumn("room", c("rest") - (c("upto") - c("words")))  # words still to take when this block comes
             .withColumn("part", F.when(c("room") <= 0, F.lit(0)).when(c("room") >= c("words"), F.lit(2)).otherwise(F.lit(1)))
             .withColumn("draws", c("passes") + (c("part") > 0).cast("int")))
    dealt = materialize(dealt, "mix-dealt")
    counts = {r[0]: int(r[1]) for r in dealt.groupBy("key").agg(F.sum("draws")).collect()}  # a row per source
    quotas = split_quotas([counts.get(p[0], 0) for p in plan], shards, int.from_bytes(hashlib.sha256(str(seed).encode()).digest()[:8], "big"))
    ranges, at = [], [0] * len(plan)
    for s, row in enumerate(quotas):
        for i, n in enumerate(row):
            if n:
                ranges.append((plan[i][0], s, at[i], at[i] + n))
                at[i] += n
    ranges_df = spark.createDataFrame(ranges, "key string, shard int, first long, beyond long")
    turn = Window.partitionBy("key").orderBy(F.xxhash64(F.lit(seed + 2), "key", "block", "pass"), "block", "pass")
    shard_of = (dealt.filter("draws > 0").select("key", "block", F.explode(F.sequence(F.lit(1), c("draws"))).alias("pass"))
                .withColumn("turn", F.row_number().over(turn) - 1)
                .join(F.broadcast(ranges_df) if len(ranges) <= BROADCAST_ROWS else ranges_df, "key").filter("turn >= first and turn < beyond")
                .groupBy("key", "block").agg(F.transform(F.array_sort(F.collect_list(F.struct("pass", "shard"))), lambda x: x["shard"]).alias("shards")))
    # the one block of a source in which its quota ends is cut after a row key; only keys and sizes are sorted
    edge = in_block.join(F.broadcast(dealt.filter("part = 1").select("key", "block", "room")), ["key", "block"])
    alike = edge.groupBy("key", "k1", "k2").agg(F.sum("size").alias("size"), F.max("room").alias("room"))
    upto = alike.withColumn("before", F.sum("size").over(Window.partitionBy("key").orderBy("k1", "k2")) - c("size")).filter(c("before") + c("size") / 2 <= c("room"))
    cuts = upto.groupBy("key").agg(F.max(F.struct("k1", "k2")).alias("last")).select("key", c("last.k1").alias("cut1"), c("last.k2").alias("cut2"))
    found = materialize(dealt.join(shard_of, ["key", "block"], "left").join(cuts, "key", "left")
                        .select("key", "block", "source_size", "target", "part", "passes", "cut1", "cut2", F.coalesce("shards", F.array().cast("array<int>")).alias("shards")), "mix-plan")
    small = found.count() <= BROADCAST_ROWS
    told = found.select(c("key").alias(key_), c("block").alias(block_), c("source_size").alias("mix_source_size"), c("target").alias("mix_target"), c("part").alias(part_), c("passes").alias(passes_), c("cut1").alias(c1), c("cut2").alias(c2), c("shards").alias(shards_))
    placed = mixed.join(F.broadcast(plans.select(c("key").alias(key_), c("blocks").alias(n_))), key_).withColumn(block_, block_of(k1, k2, c(n_)))
    rows = placed.join(F.broadcast(told) if small else told, [key_, block_])
    over = (c(part_) == 1) & ~F.coalesce((c(k1) < c(c1)) | (c(k1) == c(c1)) & (c(k2) <= c(c2)), F.lit(False))
    rows = rows.withColumn("mix_shards", F.when(over, F.slice(shards_, 1, c(passes_))).otherwise(c(shards_)))
    orders = F.transform("mix_shards", lambda s, i: F.xxhash64(F.lit(seed + 4), s, i, k1, k2))
    return rows.withColumn("mix_orders", orders).select(*docs.columns, "mix_size", "mix_source_size", "mix_target", "mix_shards", "mix_orders")


def mixed_rows(docs: DataFrame, shards: int = 16, **how) -> DataFrame:
    """The mix itself: ``docs`` columns plus ``mix_shard, mix_order``, a row per draw; every shard lies shuffled, in ascending ``mix_order``.

    One exchange: each shard is cut into ranges of the order, a partition
    holds whole ranges and is sorted. Nulls, empty texts, repeated rows and an
    empty table are as in :func:`draw`.
    """
    drawn = draw(docs, shards=shards, **how)
    both = fresh_names(drawn, "both")[0]
    rows = drawn.withColumn(both, F.explode(F.arrays_zip("mix_shards", "mix_orders"))).select(*docs.columns, F.col(f"{both}.mix_shards").alias("mix_shard"), F.col(f"{both}.mix_orders").alias("mix_order"))
    ranges = max(1, -(-2 * int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")) // shards))
    piece = F.floor((F.col("mix_order").cast("double") / 2.0 ** 64 + 0.5) * ranges)
    return rows.repartition(F.col("mix_shard"), piece).sortWithinPartitions("mix_shard", "mix_order")


def write_mix(mixed: DataFrame, path: str) -> None:
    """A folder per shard; the files of a shard, each in ascending ``mix_order``, cover ranges of it that do not overlap."""
    mixed.write.mode("overwrite").partitionBy("mix_shard").parquet(path)


def op3_hypergeometric_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    sized = materialize(documents(spark, sf_dir).select("doc_id", "source", word_count(text_or_empty("text")).alias("size")), "mix-sizes")  # words are counted once
    found = draw(sized, size=F.col("size"))
    return found.select("doc_id", "size", F.col("mix_source_size").alias("source_size"), F.col("mix_target").alias("target"), (F.col("size") * F.size("mix_shards")).cast("long").alias("taken"), "source", "mix_shards", "mix_orders")
