"""Seeded draws: every random choice is a hash of seed, purpose and position, whatever the data's layout."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gossamer.config import DescentConfig
from gossamer.functions.arrays import hash_hex, hash_int


#: Drawn places (about 60 bytes each) that are broadcast at most.
BROADCAST_ROWS = 100_000


def exact_rank(df: DataFrame, key: Column, *ties: str, most: int | None = None, by: tuple[str, ...] = (), groups: int = 1) -> DataFrame:
    """Adds ``rank``, the 0-based place in the order of a hexadecimal ``key``, without a global sort.

    Rows are counted in the buckets of the first digits; a bucket's rows are numbered on their own. With ``most`` only
    the first ranks stay, and buckets beyond them are cut below the shuffle: at most ``most`` rows and one bucket move.
    ``by``: places within each of ``groups`` groups. Equal keys are ordered by ``ties``; null ids by the hash of nothing.
    """
    digits = max(1, 4 - math.ceil(math.log(max(1, groups), 16)))
    own = list(by)
    keyed = df.withColumn("__key", key).withColumn("__bucket", F.substring("__key", 1, digits))
    sizes = keyed.groupBy(*own, "__bucket").agg(F.count("*").alias("n"))  # 65,536 rows at most, or 16 a group
    before = sizes.select(*own, "__bucket", (F.sum("n").over(Window.partitionBy(*own).orderBy("__bucket")) - F.col("n")).alias("__before"))
    if most is not None:
        before = before.where(F.col("__before") < most)
    near = keyed.join(F.broadcast(before), [*own, "__bucket"])
    inside = F.row_number().over(Window.partitionBy(*own, "__bucket").orderBy("__key", *ties)) - 1
    ranked = near.withColumn("__inside", inside).withColumn("rank", (F.col("__before") + F.col("__inside")).cast("long")).drop("__key", "__bucket", "__before", "__inside")
    return ranked if most is None else ranked.where(F.col("rank") < most)


def assign_workers(points: DataFrame, n: int, seed: int, m: int | None = None, remainder: str = "drop", budget: int | None = None) -> DataFrame:
    """Adds ``worker`` and ``pos``: a random partition in random local order. ``budget``: only the first ranks.

    Cases: repeated rows and repeated ids count as samples of their own; an empty table gives no rows.
    """
    least = [] if remainder == "spread" else [(points.count() if m is None else m) // n * n]
    least += [budget] if budget is not None else []
    ranked = exact_rank(points, hash_hex(F.lit(seed), F.lit("part"), "sample_id"), "sample_id", most=min(least) if least else None)
    return ranked.withColumn("worker", F.pmod("rank", F.lit(n)).cast("int")).withColumn("pos", F.floor(F.col("rank") / n).cast("long")).drop("rank")


def foremost(points: DataFrame, seed: int, most: int) -> DataFrame:
    """The first ``most`` samples of the exact partition's order: all that a walk of so many samples draws, by however many workers.

    ``minibatches`` of these, given the whole table's number of samples, equal those of the whole table.
    """
    return exact_rank(points, hash_hex(F.lit(seed), F.lit("part"), "sample_id"), "sample_id", most=most).select(points.columns)


def hashed_workers(points: DataFrame, n: int, seed: int) -> DataFrame:
    """The cheap partition: a worker by hash, sizes equal up to chance, no rank."""
    return points.withColumn("worker", F.pmod(hash_int(F.lit(seed), F.lit("part"), "sample_id"), F.lit(n)).cast("int"))


def scanned_workers(points: DataFrame, n: int) -> DataFrame:
    """No partition at all: a worker has the samples of the tasks that read them. It depends on the layout."""
    return points.withColumn("worker", F.pmod(F.spark_partition_id(), F.lit(n)).cast("int"))


def local_order(parted: DataFrame, seed: int, epoch: int = 0, workers: int = 4096) -> DataFrame:
    """A fresh order on every worker for an epoch: ``pos`` from 0. A worker's samples are numbered in buckets, not in one task."""
    key = hash_hex(F.lit(seed), F.lit("order"), F.lit(epoch), "sample_id")
    return exact_rank(parted, key, "sample_id", by=("worker",), groups=workers).withColumnRenamed("rank", "pos")


def minibatches(points: DataFrame, cfg: DescentConfig, m: int | None = None) -> DataFrame:
    """``worker, round, slot, sample_id, x``: what each worker draws in each round, and nothing else.

    Drawn by walking the local order, the budget of n * b * steps samples is cut before any sample moves. With replacement,
    (worker, round, slot) is matched to a position by its hash; ids are ranked without their samples, which join last.
    By hash or scan a worker walks its own samples once, in local order: one that has too few draws less in its last rounds.
    """
    n, b = cfg.workers, cfg.b
    if cfg.partition != "exact":
        placed = hashed_workers(points, n, cfg.seed) if cfg.partition == "hash" else scanned_workers(points, n)
        key = hash_hex(F.lit(cfg.seed), F.lit("order"), F.lit(0), "sample_id")
        walked = exact_rank(placed, key, "sample_id", most=b * cfg.steps, by=("worker",), groups=n)
        return walked.select("worker", F.floor(F.col("rank") / b).cast("int").alias("round"), F.pmod("rank", F.lit(b)).cast("int").alias("slot"), "sample_id", "x")
    if cfg.draw == "shuffle":
        m = points.count() if m is None else m
        rounds = -(-cfg.steps * b * n // (m // n * n)) if m >= n else 1
        first = assign_workers(points, n, cfg.seed, m, budget=n * b * cfg.steps)
        drawn = first.select("worker", "pos", "sample_id", "x")
        if rounds > 1:  # later epochs: a fresh local order each, all in one plan
            every = assign_workers(points, n, cfg.seed, m).drop("pos").withColumn("epoch", F.explode(F.sequence(F.lit(1), F.lit(rounds - 1))))
            key = hash_hex(F.lit(cfg.seed), F.lit("order"), "epoch", "sample_id")
            again = exact_rank(every, key, "sample_id", by=("worker", "epoch"), groups=n * (rounds - 1))
            drawn = drawn.unionByName(again.select("worker", (F.col("rank") + F.col("epoch") * F.lit(m // n)).cast("long").alias("pos"), "sample_id", "x"))
        cut = drawn.withColumn("round", F.floor(F.col("pos") / b).cast("int")).where(F.col("round") < cfg.steps)
        return cut.select("worker", "round", F.pmod("pos", F.lit(b)).cast("int").alias("slot"), "sample_id", "x")
    m = points.count() if m is None else m
    spark = points.sparkSession
    slots = spark.range(n * cfg.steps * b).select(F.pmod("id", F.lit(n)).cast("int").alias("worker"), F.pmod(F.floor(F.col("id") / n), F.lit(cfg.steps)).cast("int").alias("round"), F.floor(F.col("id") / (n * cfg.steps)).cast("int").alias("slot"))
    whole = cfg.draw_from == "global"
    wanted = slots.withColumn("pos", F.pmod(hash_int(F.lit(cfg.seed), F.lit("draw"), "worker", "round", "slot"), F.lit(m if whole else m // n)))
    places = assign_workers(points.select("sample_id"), 1 if whole else n, cfg.seed, m)
    # as many rows as the budget: broadcast where that is few, so that neither ids nor samples are shuffled to meet them
    few = F.broadcast if n * b * cfg.steps <= BROADCAST_ROWS else lambda rows: rows
    drawn = places.drop("worker").join(few(wanted), "pos") if whole else places.join(few(wanted), ["worker", "pos"])
    return points.select("sample_id", "x").join(few(drawn), "sample_id").select("worker", "round", "slot", "sample_id", "x")


def sends(spark: SparkSession, cfg: DescentConfig) -> DataFrame:
    """``sender, sent_round, recipient, due_round, buffer``: every message of a run; it depends on the seed alone."""
    n = cfg.workers
    if cfg.comm == "silent" or n < 2:
        return spark.createDataFrame([], "sender int, sent_round int, recipient int, due_round int, buffer int")
    rows = spark.range(n * cfg.steps).select(F.pmod("id", F.lit(n)).cast("int").alias("sender"), F.floor(F.col("id") / n).cast("int").alias("sent_round"))
    return addressed(rows.where((F.col("sent_round") + 1) % cfg.comm_every == 0), cfg)


def addressed(rows: DataFrame, cfg: DescentConfig) -> DataFrame:
    """The messages of workers that send: ``sender, sent_round`` with recipients, due rounds and buffers, ``fanout`` of each."""
    n, s = cfg.workers, F.lit(cfg.seed)
    rows = rows.select("sender", "sent_round", F.explode(F.sequence(F.lit(0), F.lit(cfg.fanout - 1))).alias("copy"))
    own = cfg.threads if cfg.scope == "other_node" else 1  # workers that a sender leaves out: its node's, or itself
    base = F.col("sender") if own == 1 else F.floor(F.col("sender") / own) * own + own - 1
    offset = F.pmod(hash_int(s, F.lit("to"), "sender", "sent_round") + F.col("copy"), F.lit(n - own)) + 1
    drawn = hash_int(s, F.lit("age"), "sender", "sent_round", "copy")
    # geometric: each age half as likely as the one before, by the trailing bits of the hash
    halves = [F.when(F.pmod(drawn, F.lit(2**a)) == 0, 1).otherwise(0) for a in range(1, cfg.max_age)]
    age = F.pmod(drawn, F.lit(cfg.max_age)) + 1 if cfg.delay == "uniform" else sum(halves, F.lit(1))
    buffer = F.pmod(hash_int(s, F.lit("buffer"), "sender", "sent_round", "copy"), F.lit(cfg.buffers))
    return rows.select("sender", "sent_round", F.pmod(base + offset, F.lit(n)).cast("int").alias("recipient"), (F.col("sent_round") + age).cast("int").alias("due_round"), buffer.cast("int").alias("buffer"))


def blocks(messages: DataFrame, cfg: DescentConfig) -> DataFrame:
    """A row a block sent: all of a state, or the ``block_frac`` share drawn for the message."""
    each = messages.withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(cfg.k - 1))))
    share = max(1, round(cfg.block_frac * cfg.k))
    if share >= cfg.k:
        return each
    order = Window.partitionBy("sender", "sent_round").orderBy(hash_hex(F.lit(cfg.seed), F.lit("block"), "sender", "sent_round", "block"), "block")
    return each.withColumn("n", F.dense_rank().over(order)).where(F.col("n") <= share).drop("n")


def settle(parts: DataFrame, race: str) -> DataFrame:
    """``recipient, round, buffer, block, sender, sent_round``: what stands in the buffers when they are read.

    overwrite: the last message of a buffer, whole; torn: the last writer of each block; none: all messages.
    """
    got = parts.withColumnRenamed("due_round", "round")
    if race == "none":
        return got.select("recipient", "round", "buffer", "block", "sender", "sent_round")
    last = F.max(F.struct("sent_round", "sender"))
    keys = ["recipient", "round", "buffer"] + ["block"] * (race == "torn")
    winners = got.groupBy(*keys).agg(last.alias("last")).select(*keys, F.col("last.sent_round").alias("sent_round"), F.col("last.sender").alias("sender"))
    return got.select("recipient", "round", "buffer", "block", "sender", "sent_round").join(winners, [*keys, "sent_round", "sender"], "left_semi") if race == "overwrite" else winners.select("recipient", "round", "buffer", "block", "sender", "sent_round")


def inbox(spark: SparkSession, cfg: DescentConfig, messages: DataFrame | None = None) -> DataFrame:
    """The settled mail of a run, or of ``messages``. Without ``consume`` what stands in a buffer is there in each round until the next arrives."""
    stood = settle(blocks(sends(spark, cfg) if messages is None else messages, cfg), cfg.race).where(F.col("round") < cfg.steps)
    if cfg.consume:
        return stood
    keys = ["recipient", "buffer"] + ["block"] * (cfg.race == "torn")
    arrivals = stood.select(*keys, "round").distinct()
    until = arrivals.withColumn("until", F.lead("round", 1, cfg.steps).over(Window.partitionBy(*keys).orderBy("round")))
    return stood.join(until, [*keys, "round"]).select("recipient", F.explode(F.sequence(F.col("round"), F.col("until") - 1)).alias("round"), "buffer", "block", "sender", "sent_round")


def newest(reads: DataFrame, messages: DataFrame) -> DataFrame:
    """``worker, t, sender, sent_round``: the newest message sent to a reader no later than each of its rounds ``worker, t``.

    Reads and messages meet in one order of rounds, so that no reader meets every message. What nobody has written to is left out.
    """
    sent = messages.groupBy(F.col("recipient").alias("worker"), F.col("sent_round").alias("t")).agg(F.max("sender").alias("sender"))
    both = sent.select("worker", "t", F.struct("sender", F.col("t").alias("sent_round")).alias("m"), F.lit(False).alias("read")).unionByName(reads.select("worker", "t", F.lit(True).alias("read")), allowMissingColumns=True)
    # a round's messages come before its reads
    last = F.last("m", ignorenulls=True).over(Window.partitionBy("worker").orderBy("t", "read").rowsBetween(Window.unboundedPreceding, 0))
    return both.withColumn("m", last).where("read and m is not null").select("worker", "t", "m.sender", "m.sent_round")


def race_counts(messages: DataFrame, settled: DataFrame) -> DataFrame:
    """A row a round: messages due, messages lost to overwriting, buffers with blocks of several senders."""
    due = messages.groupBy(F.col("due_round").alias("round")).agg(F.count("*").alias("due"))
    stood = settled.groupBy("round").agg(F.count_distinct("recipient", "sender", "sent_round", "buffer").alias("kept"))
    torn = settled.groupBy("round", "recipient", "buffer").agg(F.count_distinct("sender", "sent_round").alias("n")).groupBy("round").agg(F.sum((F.col("n") > 1).cast("long")).alias("torn"))
    return due.join(stood, "round").join(torn, "round").select("round", F.col("due").cast("long").alias("due"), (F.col("due") - F.col("kept")).cast("long").alias("lost"), "torn")


def hash_sample(df: DataFrame, share: float, seed: int, key: str = "sample_id") -> DataFrame:
    """A seeded share of the rows, the same whatever the layout."""
    return df.where(hash_int(F.lit(seed), F.lit("sample"), key) < int(share * 2**32))
