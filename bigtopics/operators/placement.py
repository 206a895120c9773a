"""Placing words and documents on shards, block schedules and balance."""

from __future__ import annotations

import heapq

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.rand import uniform
from ..sources.files import settle


def weighted_placement(counts: list[tuple[int, int]], shards: int) -> list[tuple[int, int]]:
    """(word, shard): heaviest first to the least loaded shard; ties go to the smaller id and shard."""
    loads = [(0, s) for s in range(shards)]
    out = []
    for word, tf in sorted(counts, key=lambda x: (-x[1], x[0])):
        load, s = heapq.heappop(loads)
        out.append((word, s))
        heapq.heappush(loads, (load + tf, s))
    return out


def assign_words(vocab: DataFrame, shards: int, method: str = "hash", *, head: int = 100_000) -> DataFrame:
    """vocab (word_id, tf) with word_shard.

    hash; rank (round robin by frequency); snake (back and forth by frequency);
    weighted (greedy on the driver, for at most ``head`` words); hybrid (the
    ``head`` most frequent words greedily, all others by hash).
    """
    hashed = F.pmod(F.xxhash64("word_id"), F.lit(shards)).cast("bigint")
    if method == "hash":
        return vocab.withColumn("word_shard", hashed)
    if method in ("rank", "snake"):
        r = F.col("rank")
        back = F.when((F.floor(r / shards) % 2) == 1, shards - 1 - r % shards).otherwise(r % shards)
        ranked = ranked_by_tf(vocab)
        return ranked.withColumn("word_shard", (r % shards if method == "rank" else back).cast("bigint")).drop("rank")
    top = vocab.orderBy(F.desc("tf"), "word_id").limit(head)
    placed = weighted_placement([(r.word_id, r.tf) for r in top.select("word_id", "tf").collect()], shards)
    if method == "weighted" and len(placed) == head and vocab.count() > head:
        raise ValueError(f"weighted placement holds at most {head} words; use hybrid")
    table = vocab.sparkSession.createDataFrame(placed, "word_id bigint, placed bigint")
    return vocab.join(table, "word_id", "left").withColumn("word_shard", F.coalesce("placed", hashed)).drop("placed")


def check_shard_size(rows: DataFrame, max_bytes: int, *, entry_bytes: int = 8, refuse: bool = True) -> DataFrame:
    """shard, bytes, fits: bytes of each shard's entries against what a worker may hold; by default a shard beyond it is refused."""
    sizes = rows.groupBy("shard").agg((F.count(F.lit(1)) * entry_bytes).alias("bytes")).withColumn("fits", F.col("bytes") <= max_bytes)
    if refuse and (worst := sizes.filter("not fits").orderBy(F.desc("bytes")).first()):
        raise ValueError(f"shard {worst.shard} takes {worst.bytes} bytes; the limit is {max_bytes}: use more shards")
    return sizes


def ranked_by_tf(vocab: DataFrame, parts: int = 32) -> DataFrame:
    """vocab with its rank (from 0) by descending tf, then id, from range-sorted partitions."""
    # written: bounds are sampled, so two runs of the same plan could cut differently
    ranged = settle(vocab.repartitionByRange(parts, F.desc("tf"), "word_id").withColumn("__p", F.spark_partition_id()), "ranged")
    sizes = ranged.groupBy("__p").agg(F.count(F.lit(1)).alias("__n"))
    base = sizes.select("__p", (F.sum("__n").over(Window.orderBy("__p")) - F.col("__n")).alias("__b"))
    local = ranged.withColumn("__r", F.row_number().over(Window.partitionBy("__p").orderBy(F.desc("tf"), "word_id")))
    return local.join(F.broadcast(base), "__p").withColumn("rank", (F.col("__r") - 1 + F.col("__b")).cast("bigint")).drop("__p", "__r", "__b")


def doc_shard(shards: int, seed: int = 7, id_col: str = "doc_id") -> Column:
    return F.floor(uniform(F.lit("doc"), id_col, seed=seed) * shards).cast("bigint")


def word_shard(shards: int, seed: int = 7, id_col: str = "word_id") -> Column:
    return F.floor(uniform(F.lit("word"), id_col, seed=seed) * shards).cast("bigint")


def diagonal(doc: Column, word: Column, shards: int) -> Column:
    """The step in which a block runs: blocks of one step share no row and no column."""
    return F.pmod(doc - word, F.lit(shards)).cast("bigint")


def schedule(spark: SparkSession, shards: int) -> DataFrame:
    """step, doc_shard, word_shard of all blocks."""
    d = spark.range(shards * shards).select(F.floor(F.col("id") / shards).cast("bigint").alias("doc_shard"), (F.col("id") % shards).alias("word_shard"))
    return schedule_of(d, shards)


def schedule_of(blocks: DataFrame, shards: int) -> DataFrame:
    """The same of the blocks at hand: doc_shard, word_shard, of blocks or of their tokens."""
    d = blocks.select("doc_shard", "word_shard").distinct()
    return d.select(diagonal(F.col("doc_shard"), F.col("word_shard"), shards).alias("step"), "doc_shard", "word_shard")


def conflicts(plan: DataFrame) -> DataFrame:
    """Pairs of blocks of one step that share a shard; a right schedule has none."""
    a, b = plan.alias("a"), plan.alias("b")
    same = ((F.col("a.doc_shard") == F.col("b.doc_shard")) & (F.col("a.word_shard") < F.col("b.word_shard"))) | ((F.col("a.word_shard") == F.col("b.word_shard")) & (F.col("a.doc_shard") < F.col("b.doc_shard")))
    return a.join(b, F.col("a.step") == F.col("b.step")).filter(same).select(F.col("a.step").alias("step"), F.col("a.doc_shard").alias("d1"), F.col("a.word_shard").alias("w1"), F.col("b.doc_shard").alias("d2"), F.col("b.word_shard").alias("w2"))


def balance_report(loads: DataFrame, load: str = "load") -> DataFrame:
    """shards, largest load over the mean, coefficient of variation, idle share at a barrier."""
    a = loads.agg(F.count(F.lit(1)).alias("shards"), F.max(load).alias("mx"), F.avg(load).alias("mean"), F.stddev_pop(load).alias("sd"))
    return a.select("shards", F.round(F.col("mx") / F.col("mean"), 6).alias("max_over_mean"), F.round(F.col("sd") / F.col("mean"), 6).alias("cv"), F.round(1 - F.col("mean") / F.col("mx"), 6).alias("idle_share"))


def schedule_free(costs: dict[tuple[int, int], float], shards: int, extra: int = 1, rounds: int = 1) -> list[tuple[int, int, int, float, float]]:
    """Lock-free schedule with spare document shards: (worker, doc shard, word shard, start, end).

    Word shards stay with their worker.  A worker that ends takes, among document
    shards nobody holds, the one it has visited least.
    """
    docs = shards + extra
    left = {w: [rounds] * docs for w in range(shards)}
    free, events, queue = set(range(docs)), [], [(0.0, w, -1) for w in range(shards)]
    waiting: list[int] = []
    heapq.heapify(queue)
    while queue:
        now, w, held = heapq.heappop(queue)
        if held >= 0:
            free.add(held)
        for v in [*waiting, w]:
            open_ = [d for d in free if left[v][d] > 0]
            if v in waiting:
                waiting.remove(v)
            if open_:
                d = max(open_, key=lambda x: (left[v][x], -x))
                left[v][d] -= 1
                free.discard(d)
                end = now + costs.get((d, v), 1.0)
                events.append((v, d, v, now, end))
                heapq.heappush(queue, (end, v, d))
            elif any(left[v]):
                waiting.append(v)
    return events
