"""Nearest neighbours by inner product with adaptive dimension scans.

Vectors are lifted by one coordinate so that the largest inner product is the smallest distance, rotated by a
random orthogonal matrix, and put into inverted lists around centroids. A list's vectors lie in
column blocks. For each query that probes the list, blocks of coordinates are added one by one; after each,
a hypothesis test on the partial distance abandons the candidates that are, with high confidence,
farther than the query's threshold. Threshold and first neighbours come from a sample of at most ``SAMPLE``
vectors, which also fits centroids and chooses the number of probes by measured recall; every vector is in
the index. Survivors get their exact score on original vectors, in double precision and coordinate order.

Equal vectors are searched once: only the ``k + 1`` smallest ids of a vector can be among any query's
neighbours. Lists are cut into cells of at most about ``CELL`` vectors and ``CELL`` queries.

Cases: vectors that are null, zero, or hold null or non-finite components take no part; vectors of several lengths are
searched length by length; ties go to the smaller id; repeated ids count once for each different vector; fewer candidates than ``k`` give fewer rows; an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import common

SAMPLE, CELL, MOST_LISTS = 8192, 8192, 4096
MOST_DEPTHS = 64  #: different lengths of vectors that ask
BLOCK = 16  #: coordinates of a column block
CONFIDENCE = 2.1  #: of the hypothesis test: candidates go at partial distance > threshold * (1 + CONFIDENCE / sqrt(m))
RECALL = 0.97  #: aimed at on the sample, when the number of probes is chosen


def usable(x: Column) -> Column:
    fine = F.forall(x, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf")))
    return x.isNotNull() & (F.size(x) > 0) & F.coalesce(fine, F.lit(False)) & F.coalesce(F.exists(x, lambda v: v != 0), F.lit(False))


def exact_scores(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Row-wise inner products, summed in coordinate order in double precision."""
    total = np.zeros(len(x))
    for j in range(x.shape[1]):
        total += q[..., j].astype(np.float64) * x[:, j].astype(np.float64)
    return total


@dataclass
class Index:
    """What every task needs: all of bounded size."""

    top: float  # largest squared norm
    rotation: np.ndarray
    centroids: np.ndarray  # of lifted, rotated vectors
    sample: np.ndarray  # lifted, rotated
    original: np.ndarray
    keys: list[str]
    ids: list[list[int]]
    probes: int

    def lifted(self, x: np.ndarray) -> np.ndarray:
        x = x.astype(np.float64)
        rest = np.sqrt(np.maximum(self.top - (x * x).sum(axis=1), 0))
        return (np.concatenate([x, rest[:, None]], axis=1) @ self.rotation).astype(np.float32)

    def lifted_query(self, x: np.ndarray) -> np.ndarray:
        return (np.concatenate([x.astype(np.float64), np.zeros((len(x), 1))], axis=1) @ self.rotation).astype(np.float32)


def squared_distances(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.maximum((a * a).sum(axis=1)[:, None] - 2 * (a @ b.T) + (b * b).sum(axis=1), 0)


def centroids_of(x: np.ndarray, k: int, rng: np.random.Generator, rounds: int = 8) -> np.ndarray:
    at = x[rng.choice(len(x), k, replace=False)].copy()
    for _ in range(rounds):
        near = squared_distances(x, at).argmin(axis=1)
        counts = np.bincount(near, minlength=k)
        sums = np.zeros_like(at)
        np.add.at(sums, near, x)
        at = np.where(counts[:, None] > 0, sums / np.maximum(counts, 1)[:, None], at)
    return at


def fitted(sample: pa.Table, n: int, top: float, k: int, most_lists: int = MOST_LISTS, seed: int = 11) -> Index:
    rng = np.random.default_rng(seed)
    original = np.ascontiguousarray(_matrix(sample.column("embedding").combine_chunks()))
    rows = range(len(original))
    depth = original.shape[1]
    q, r = np.linalg.qr(rng.normal(size=(depth + 1, depth + 1)))
    index = Index(top, q * np.sign(np.diag(r)), np.zeros((1, depth + 1)), np.zeros(0), original, sample.column("key").to_pylist(), sample.column("ids").to_pylist(), 1)
    index.sample = index.lifted(original)
    lists = max(1, min(most_lists, int(np.sqrt(n)), len(rows)))
    index.centroids = centroids_of(index.sample, lists, rng)
    # probes: the fewest with which the lists cover RECALL of the sample's own neighbours
    asked = rng.choice(len(rows), min(256, len(rows)), replace=False)
    home = squared_distances(index.sample, index.centroids).argmin(axis=1)
    queries = index.lifted_query(original[asked])
    far = squared_distances(queries, index.sample)
    far[np.arange(len(asked)), asked] = np.inf
    order = squared_distances(queries, index.centroids).argsort(axis=1)
    place = np.empty_like(order)
    np.put_along_axis(place, order, np.arange(lists)[None, :].repeat(len(asked), 0), axis=1)
    nearest = far.argsort(axis=1)[:, : min(k, len(rows) - 1)]
    if nearest.size:
        index.probes = int(np.quantile(np.take_along_axis(place, home[nearest], axis=1), RECALL, method="higher")) + 1
    return index


def scan(blocks: list[np.ndarray], query: np.ndarray, threshold: float) -> np.ndarray:
    """Rows whose distance may be within ``threshold`` (squared): partial distances, tested after each column block."""
    depth, seen = len(query), 0
    alive = np.arange(len(blocks[0]))
    far = np.zeros(len(alive), np.float32)
    for block in blocks:
        own = block if len(alive) == len(block) else block[alive]
        d = own - query[seen : seen + block.shape[1]]
        far += np.einsum("ij,ij->i", d, d)
        seen += block.shape[1]
        limit = threshold * (1 + 1e-5) if seen == depth else threshold * seen / depth * (1 + CONFIDENCE / seen**0.5) ** 2
        keep = far <= limit + 1e-6
        if not keep.all():
            alive, far = alive[keep], far[keep]
            if not len(alive):
                break
    return alive


def search(vectors: DataFrame, queries: Column, k: int = 20, sample: int = SAMPLE, most_lists: int = MOST_LISTS) -> DataFrame:
    """``query_id, rank, vec_id, score``: for each row of ``vectors (vec_id, embedding)`` where ``queries`` holds.

    Vectors of different lengths have no inner product: each length is searched by itself. ``sample`` and
    ``most_lists`` bound what the index is fitted on; a query's work grows with the vectors a list, so raise both with the table.
    """
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("embedding"), F.coalesce(queries, F.lit(False)).alias("asks")).where(F.col("vec_id").isNotNull() & usable(F.col("embedding")))
    depths = [r.depth for r in rows.where("asks").select(F.size("embedding").alias("depth")).distinct().orderBy("depth").limit(MOST_DEPTHS + 1).collect()]
    if len(depths) > MOST_DEPTHS:
        raise ValueError(f"more than {MOST_DEPTHS} lengths of vectors")
    found = [_search(rows.where(F.size("embedding") == d), k, sample, most_lists) for d in depths]
    return reduce(DataFrame.unionByName, found) if found else vectors.sparkSession.createDataFrame([], "query_id long, rank int, vec_id long, score double")


def _search(rows: DataFrame, k: int, most: int, most_lists: int) -> DataFrame:
    """``search`` among usable vectors of one length."""
    spark = rows.sparkSession
    rows = rows.withColumn("key", F.concat(F.hex(F.xxhash64("embedding")), F.hex(F.xxhash64(F.lit(1), "embedding"))))
    few = rows.withColumn("n", F.dense_rank().over(Window.partitionBy("key").orderBy("vec_id"))).where(F.col("n") <= k + 1)
    classes = common.settled(few.groupBy("key").agg(F.array_sort(F.collect_set("vec_id")).alias("ids"), F.first("embedding").alias("embedding")), "vectors")
    n, top = classes.agg(F.count("*"), F.max(F.aggregate("embedding", F.lit(0.0), lambda s, v: s + v * v))).first()
    placed_first = classes.withColumn("h", common.place("key")).where(F.col("h") < common.likely(most, F.lit(n)))
    sample = placed_first.orderBy("h", "key").limit(most).select("key", "ids", "embedding").toArrow()  # so many rows at most
    index = fitted(sample, n, top, k, most_lists)
    sent = spark.sparkContext.broadcast(index)
    asking = rows.where("asks").select("vec_id", "key")
    asked = classes.select("key", "embedding").join(asking.select("key").distinct(), "key", "left_semi")

    def place(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = sent.value
        for batch in batches:
            if batch.num_rows:
                x = _matrix(batch.column(2))
                near = np.concatenate([squared_distances(own.lifted(x[a : a + 4096]), own.centroids).argmin(axis=1) for a in range(0, len(x), 4096)])
                yield pa.RecordBatch.from_arrays([pa.array(near.astype(np.int32)), batch.column(0), batch.column(1), batch.column(2)], ["list", "key", "ids", "embedding"])

    placed = common.settled(classes.select("key", "ids", "embedding").mapInArrow(place, "list int, key string, ids array<long>, embedding array<double>"), "lists")
    sizes = np.zeros(len(index.centroids), np.int64)
    for r in placed.groupBy("list").count().collect():  # MOST_LISTS rows at most
        sizes[r["list"]] = r["count"]

    def route(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = sent.value
        for whole in batches:
            for start in range(0, whole.num_rows, 512):
                batch = whole.slice(start, 512)
                x = _matrix(batch.column(1))
                q = own.lifted_query(x)
                order = squared_distances(q, own.centroids).argsort(axis=1, kind="stable")
                reach = np.cumsum(sizes[order], axis=1)
                probes = np.maximum(own.probes, (reach < k + 1).sum(axis=1) + 1)
                far = squared_distances(q, own.sample)
                m = min(k + 1, far.shape[1])
                best = np.argpartition(far, m - 1, axis=1)[:, :m]
                limit = np.take_along_axis(far, best, axis=1).max(axis=1) if m == k + 1 else np.full(len(x), np.inf)
                seeds = [[{"key": own.keys[j], "ids": own.ids[j], "score": float(s)} for j, s in zip(b.tolist(), exact_scores(x[i], own.original[b]), strict=True)] for i, b in enumerate(best)]
                lists = [o[:p][sizes[o[:p]] > 0].tolist() for o, p in zip(order, probes, strict=True)]
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(limit.astype(np.float64)), pa.array(lists, pa.list_(pa.int32())), pa.array(seeds, _SEEDS)], ["asker", "query", "threshold", "lists", "seeds"])

    routed = common.settled(asked.select("key", "embedding").mapInArrow(route, "asker string, query array<double>, threshold double, lists array<int>, seeds array<struct<key: string, ids: array<long>, score: double>>"), "queries")
    probing = routed.select("asker", "query", "threshold", F.explode("lists").alias("list"))
    asks = np.zeros(len(index.centroids), np.int64)
    for r in probing.groupBy("list").count().collect():  # MOST_LISTS rows at most
        asks[r["list"]] = r["count"]
    parts = F.array(*[F.lit(int(v)) for v in np.maximum(1, -(-sizes // CELL))])
    rounds = F.array(*[F.lit(int(v)) for v in np.maximum(1, -(-asks // CELL))])
    deal = lambda key, blocks: F.pmod(F.xxhash64(key), F.element_at(blocks, F.col("list") + 1)).cast("int")
    every = lambda blocks: F.explode(F.sequence(F.lit(0), F.element_at(blocks, F.col("list") + 1) - 1))
    left = placed.withColumn("part", deal("key", parts)).withColumn("round", every(rounds))
    right = probing.withColumn("round", deal("asker", rounds)).withColumn("part", every(parts))

    def cell(vectors: pa.Table, asking: pa.Table) -> pa.Table:
        own, found = sent.value, []
        if vectors.num_rows and asking.num_rows:
            x = _matrix(vectors.column("embedding").combine_chunks())
            lifted = own.lifted(x)
            blocks = [np.ascontiguousarray(lifted[:, a : a + BLOCK]) for a in range(0, lifted.shape[1], BLOCK)]
            keys, ids = vectors.column("key").to_pylist(), vectors.column("ids").to_pylist()
            raw = _matrix(asking.column("query").combine_chunks())
            for asker, limit, q, whole in zip(asking.column("asker").to_pylist(), asking.column("threshold").to_pylist(), own.lifted_query(raw), raw, strict=True):
                alive = scan(blocks, q, limit)
                if len(alive):
                    score = exact_scores(whole, x[alive])
                    firsts = np.asarray([ids[i][0] for i in alive])
                    found += [(asker, keys[alive[j]], ids[alive[j]], float(score[j])) for j in np.lexsort((firsts, -score))[: k + 1]]
        kinds = (pa.string(), pa.string(), pa.list_(pa.int64()), pa.float64())
        return pa.table([pa.array(v, type=t) for v, t in zip(zip(*found, strict=True) if found else [[]] * 4, kinds, strict=True)], names=["asker", "key", "ids", "score"])

    cells = ("list", "part", "round")
    scanned = left.groupBy(*cells).cogroup(right.groupBy(*cells)).applyInArrow(cell, "asker string, key string, ids array<long>, score double")
    seeds = routed.select("asker", F.explode("seeds").alias("s")).select("asker", "s.key", "s.ids", "s.score")
    near = Window.partitionBy("asker")
    both = scanned.unionByName(seeds).groupBy("asker", "key").agg(F.first("ids").alias("ids"), F.max("score").alias("score"))
    best = both.withColumn("n", F.row_number().over(near.orderBy(F.desc("score"), F.col("ids")[0]))).where(F.col("n") <= k + 1)
    flat = best.select("asker", "score", F.explode("ids").alias("vec_id"))
    ranked = flat.withColumn("n", F.row_number().over(near.orderBy(F.desc("score"), "vec_id"))).where(F.col("n") <= k + 1)
    lists = ranked.groupBy("asker").agg(F.array_sort(F.collect_list(F.struct("n", "vec_id", "score"))).alias("near"))
    mine = F.slice(F.filter("near", lambda s: s["vec_id"] != F.col("query_id")), 1, k)
    out = asking.select(F.col("vec_id").alias("query_id"), "key").join(lists, F.col("key") == F.col("asker"))
    return out.select("query_id", F.posexplode(mine).alias("at", "s")).select("query_id", (F.col("at") + 1).cast("int").alias("rank"), F.col("s.vec_id").alias("vec_id"), F.col("s.score").alias("score"))


_SEEDS = pa.list_(pa.struct([("key", pa.string()), ("ids", pa.list_(pa.int64())), ("score", pa.float64())]))


def _matrix(column: pa.Array) -> np.ndarray:
    """A matrix of a list column whose rows have one length."""
    return column.flatten().to_numpy(zero_copy_only=False).reshape(len(column), -1)
