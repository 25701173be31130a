"""Point sets ``(sample_id string, x array<double>)`` on the given tables, and the planted mixture."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from gossamer.functions.arrays import hash_int


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def line4(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = table(spark, sf_dir, "lineitem")
    key = F.concat_ws("-", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    return t.select(key.alias("sample_id"), F.array(F.col("l_quantity") / 50.0, F.col("l_extendedprice") / 105000.0, F.col("l_discount") * 10.0, F.col("l_tax") * 12.5).alias("x"))


def emb64(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("string").alias("sample_id"), F.col("embedding").cast("array<double>").alias("x"))


def evt3(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = table(spark, sf_dir, "events")
    return t.select(F.col("event_id").cast("string").alias("sample_id"), F.array(F.col("value") / 600.0, F.hour("ts") / 24.0, F.get_json_object("props", "$.k").cast("double") / 100.0).alias("x"))


def doc_buckets(spark: SparkSession, sf_dir: str, buckets: int = 128) -> DataFrame:
    """``doc_id, bucket, n``: token counts by hash."""
    words = table(spark, sf_dir, "documents").select("doc_id", F.explode(F.split(F.lower("text"), "[^a-z0-9]+")).alias("token")).where("token <> ''")
    return words.groupBy("doc_id", F.pmod(hash_int(F.col("token")), F.lit(buckets)).alias("bucket")).agg(F.count("*").alias("n"))


def doc128(spark: SparkSession, sf_dir: str, buckets: int = 128) -> DataFrame:
    """Hashed token counts of each document, of unit length."""
    lists = doc_buckets(spark, sf_dir, buckets).groupBy("doc_id").agg(F.collect_list(F.struct("bucket", "n")).alias("c")).select(F.col("doc_id").cast("string").alias("sample_id"), "c")

    def dense(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # in an expression the optimizer would build a document's counts again for each of its buckets
        for batch in batches:
            counts = batch.column(1)
            x, flat = np.zeros((batch.num_rows, buckets)), counts.flatten()
            x[pc.list_parent_indices(counts).to_numpy(), flat.field("bucket").to_numpy()] = flat.field("n").to_numpy()
            x /= np.sqrt((x * x).sum(axis=1))[:, None]
            ends = pa.array(np.arange(0, x.size + 1, buckets, dtype=np.int32))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(ends, pa.array(x.ravel()))], ["sample_id", "x"])

    return lists.mapInArrow(dense, "sample_id string, x array<double>")


def acting(spark: SparkSession, sf_dir: str, workers: int) -> DataFrame:
    """``sender, sent_round``: the hours since 1970 in which a worker's users act; users are dealt out by their number."""
    hour = F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / (3600 * 10**6)).cast("int")
    return table(spark, sf_dir, "events").where("user_id is not null and ts is not null").select(F.pmod("user_id", F.lit(workers)).cast("int").alias("sender"), hour.alias("sent_round")).distinct()


def uniform(*key) -> Column:
    """A number in [0, 1) from the hash of the key."""
    return hash_int(*key) / float(2**32)


def planted(dims: int, k: int, seed: int, spread: float, min_dist: float) -> list[list[float]]:
    """Centres of which no two are nearer than ``min_dist``: each is drawn again until it keeps clear of those before."""
    from hashlib import md5

    found: list[list[float]] = []
    for c in range(k):
        for again in range(10_000):
            key = f":{again}" if again else ""
            mu = [int(md5(f"{seed}:mu:{c}:{j}{key}".encode()).hexdigest()[:8], 16) / 2**32 * spread for j in range(dims)]
            if all(sum((a - b) ** 2 for a, b in zip(mu, other, strict=True)) >= min_dist**2 for other in found):
                break
        else:
            raise ValueError("so many centres do not fit so far apart")
        found.append(mu)
    return found


def truth(spark: SparkSession, dims: int, k: int, seed: int = 1, spread: float = 10.0, sigma: float = 1.0, min_dist: float = 0.0) -> DataFrame:
    """Planted centres ``(center, mu, sigma)``."""
    if min_dist:
        return spark.createDataFrame([(c, mu, float(sigma)) for c, mu in enumerate(planted(dims, k, seed, spread, min_dist))], "center int, mu array<double>, sigma double")
    mu = F.transform(F.sequence(F.lit(0), F.lit(dims - 1)), lambda j: uniform(F.lit(seed), F.lit("mu"), F.col("id"), j) * spread)
    return spark.range(k).select(F.col("id").cast("int").alias("center"), mu.alias("mu"), F.lit(float(sigma)).alias("sigma"))


def close_centres(centres: DataFrame, least: float) -> DataFrame:
    """Pairs of centres nearer than ``least``: the generator's overlap control, a range join of k rows."""
    from gossamer.functions.arrays import sqdist

    a, b = centres.select(F.col("center").alias("a"), F.col("mu").alias("mu_a")), centres.select(F.col("center").alias("b"), F.col("mu").alias("mu_b"))
    return a.join(F.broadcast(b), F.col("a") < F.col("b")).withColumn("distance", F.sqrt(sqdist("mu_a", "mu_b"))).where(F.col("distance") < least)


def mix(spark: SparkSession, dims: int, m: int, k: int, seed: int = 1, spread: float = 10.0, sigma: float = 1.0, tasks: int | None = None, min_dist: float = 0.0) -> DataFrame:
    """``m`` samples around planted centres; the noise is a sum of twelve hashed uniforms, the same on any engine.

    ``min_dist``: centres are at least so far apart; ``sigma``: the noise. Both control how far clusters overlap.
    """
    return mixed(spark.range(0, m, 1, tasks) if tasks else spark.range(m), dims, k, seed, spread, sigma, min_dist)


def mixed(rows: DataFrame, dims: int, k: int, seed: int = 1, spread: float = 10.0, sigma: float = 1.0, min_dist: float = 0.0) -> DataFrame:
    """The mixture's sample of each row's ``id``."""
    center = F.pmod(hash_int(F.lit(seed), F.lit("c"), F.col("id")), F.lit(k))
    if min_dist:
        centres = F.array(*[F.array(*map(F.lit, mu)) for mu in planted(dims, k, seed, spread, min_dist)])
        base = lambda j: centres[center][j]
    else:
        base = lambda j: uniform(F.lit(seed), F.lit("mu"), center, j) * spread
    noise = lambda j: F.aggregate(F.sequence(F.lit(0), F.lit(11)), F.lit(-6.0), lambda s, i: s + uniform(F.lit(seed), F.lit("x"), F.col("id"), j, i))
    return rows.select(F.col("id").cast("string").alias("sample_id"), F.transform(F.sequence(F.lit(0), F.lit(dims - 1)), lambda j: base(j) + noise(j) * sigma).alias("x"))


def checked(points: DataFrame, on_bad: str = "drop") -> DataFrame:
    """Samples that are null or empty, hold null, NaN or infinity, or whose length is not the most frequent one (the longer of
    equally frequent ones): dropped, or an error. Extra columns stay."""
    fine = F.coalesce(F.forall("x", lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf"))), F.lit(False)) & (F.size("x") > 0)
    whole = points.where(F.col("x").isNotNull() & fine)
    sizes = whole.groupBy(F.size("x").alias("width")).count().orderBy(F.desc("count"), F.desc("width")).limit(2).collect()
    if on_bad != "drop" and (len(sizes) > 1 or points.where(F.col("x").isNull() | ~fine).limit(1).count()):
        raise ValueError("samples are null, not finite or ragged")
    return whole.where(F.size("x") == sizes[0].width) if sizes else whole


SETS = {"line4": line4, "emb64": emb64, "doc128": doc128, "evt3": evt3}
