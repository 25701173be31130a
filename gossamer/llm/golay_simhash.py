"""SimHash near-duplicates by Golay-code fuzzy hashing.

A 64-bit fingerprint is cut into segments A and B of 23 bits and C of 18. The binary (23, 12) Golay
code is perfect: every 23-bit word is within 3 of exactly one codeword. A segment's keys are the index
of that codeword and, at distance 3, of the five codewords at distance 4; two segments at most one bit
apart always share a key. For fingerprints at most 3 bits apart, the errors a + b + c <= 3 leave one of

* c = 0 and a <= 1, or c = 0 and b <= 1: C equal, a shared Golay key of A or of B;
* c >= 1 and a = 0, or b = 0: A equal, or B equal;
* c = 1, a = b = 1: shared Golay keys of A and of B

so five kinds of keys lose no link. Exact copies meet in one distinct fingerprint first. Rows that share a
key are verified by exclusive-or, walking each key's fingerprints from link to link, so that a dense
group of n costs about n comparisons and gives at most n - 1 links. A key of more than ``CELL`` fingerprints
is dealt into blocks, and each pair of blocks is a cell of its own. Links then become components by
alternating large-star and small-star rounds on written tables.

Cases: null and empty texts and texts without words have fingerprint zero and link to each other;
repeated doc_ids stay as rows; null doc_ids stay and give no component id of their own; texts of any
length are hashed whole; an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

import functools
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import common

CELL = 8192
A_BITS, B_BITS, C_BITS = 23, 23, 18
#: Fixed value: generator polynomial of the Golay code, x^11 + x^9 + x^7 + x^6 + x^5 + x + 1.
GOLAY_GENERATOR = 0b101011100011
_BITS = np.arange(64, dtype=np.uint64)


# --- fingerprints ------------------------------------------------------------------------------


def fingerprint(text: str, width: int = 3, seed: int = 42) -> int:
    words = text.encode("utf-8", "surrogatepass").lower().split()  # bytes: A-Z only, and ASCII white space only
    if not words:
        return 0
    digest = xxhash.xxh64_intdigest
    if len(words) <= width:
        hashes = [digest(b" ".join(words), seed)]
    else:
        line = b" ".join(words)
        ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
        starts = np.concatenate([[0], ends[:-1] + 1])
        hashes = [digest(line[a:b], seed) for a, b in zip(starts[: 1 - width].tolist(), ends[width - 1 :].tolist(), strict=True)]
    n, ones = len(hashes), np.zeros(64, np.int64)
    array = np.asarray(hashes, "<u8")
    for a in range(0, n, 1 << 16):
        bits = np.unpackbits(array[a : a + (1 << 16)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        ones += bits.sum(axis=0, dtype=np.int64)
    return int((np.uint64(1) << _BITS[2 * ones > n]).sum(dtype=np.uint64)) if (2 * ones > n).any() else 0


def fingerprints(docs: DataFrame, width: int = 3, seed: int = 42, hashed: bool = False) -> DataFrame:
    """``doc_id, fp``: the 64 bits as a signed long. ``hashed`` adds ``text_hash``."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in common.slices(batches):
            many = part.column(1).to_pylist()
            known = {t: fingerprint(t, width, seed) for t in set(many)}
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(np.asarray([known[t] for t in many], np.uint64).view(np.int64)), *part.columns[2:]], ["doc_id", "fp", *["text_hash"] * hashed])

    more = [F.xxhash64("text").alias("text_hash")] if hashed else []
    return common.texts(docs, *more).mapInArrow(run, "doc_id long, fp long" + ", text_hash long" * hashed)


# --- Golay keys ----------------------------------------------------------------------------------


def _remainders(words: np.ndarray) -> np.ndarray:
    """11-bit syndromes of 23-bit words."""
    r = words.astype(np.int64).copy()
    for shift in range(11, -1, -1):
        r ^= np.where(r >> (shift + 11) & 1, GOLAY_GENERATOR << shift, 0)
    return r


@functools.cache
def _tables() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """By syndrome: the error pattern of weight 0 to 3, its weight, and five errors of weight 4 (weight 3 only)."""
    single = _remainders(1 << np.arange(23))
    error, weight = np.zeros(2048, np.int64), np.zeros(2048, np.int64)
    others: list[list[int]] = [[] for _ in range(2048)]
    places = np.arange(23)
    for w in (1, 2, 3, 4):
        grid = np.asarray([c for c in _combinations(places.tolist(), w)])
        pattern = (1 << grid).sum(axis=1)
        syndrome = np.bitwise_xor.reduce(single[grid], axis=1)
        if w < 4:
            error[syndrome], weight[syndrome] = pattern, w
        else:
            for s, p in zip(syndrome.tolist(), pattern.tolist(), strict=True):
                others[s].append(p)
    far = np.full((2048, 5), -1, np.int64)
    for s in np.flatnonzero(weight == 3):
        far[s] = others[s]
    return error, weight, far


def _combinations(items: list[int], k: int):
    from itertools import combinations

    return combinations(items, k)


def golay_keys(words: np.ndarray) -> np.ndarray:
    """For each 23-bit word six codeword indices (the 12 information bits), -1 where there are fewer."""
    error, _, far = _tables()
    s = _remainders(words)
    near = (words ^ error[s]) >> 11
    more = np.where(far[s] >= 0, (words[:, None] ^ far[s]) >> 11, -1)
    return np.concatenate([near[:, None], more], axis=1)


def keys_of(fps: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Row number and key of every key of the unsigned fingerprints."""
    a, b, c = (fps >> np.uint64(41)).astype(np.int64), (fps >> np.uint64(18) & np.uint64(2**23 - 1)).astype(np.int64), (fps & np.uint64(2**18 - 1)).astype(np.int64)
    ga, gb = golay_keys(a), golay_keys(b)
    kinds = [
        (ga >= 0, 1 << 60 | c[:, None] << 12 | ga),
        (gb >= 0, 2 << 60 | c[:, None] << 12 | gb),
        (np.ones((len(a), 1), bool), (3 << 60 | a)[:, None]),
        (np.ones((len(a), 1), bool), (4 << 60 | b)[:, None]),
        (((ga >= 0)[:, :, None] & (gb >= 0)[:, None, :]).reshape(len(a), -1), (5 << 60 | ga[:, :, None] << 12 | gb[:, None, :]).reshape(len(a), -1)),
    ]
    rows = np.concatenate([np.nonzero(ok)[0] for ok, _ in kinds])
    return rows, np.concatenate([keys[ok] for ok, keys in kinds])


# --- links ----------------------------------------------------------------------------------------


def walk(fps: np.ndarray, radius: int) -> list[tuple[int, int]]:
    """Links that join all pairs within ``radius``: from each fingerprint reached on to the ones not reached yet."""
    links, left = [], np.arange(len(fps))
    while len(left) > 1:
        queue, left = [left[0]], left[1:]
        while queue and len(left):
            at = queue.pop()
            near = np.bitwise_count(fps[left] ^ fps[at]) <= radius
            if near.any():
                hit = left[near]
                links += [(at, int(k)) for k in hit]
                queue += hit.tolist()
                left = left[~near]
    return links


def links(distinct: DataFrame, radius: int = 3) -> DataFrame:
    """Links ``(u, v)`` between distinct fingerprints ``(fp)``; their components are those of all pairs."""
    if radius > 3:
        raise ValueError("the keys hold up to 3 differing bits")

    def keyed(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start in range(0, batch.num_rows, 8192):
                fps = batch.column(0).slice(start, 8192).to_numpy()
                rows, keys = keys_of(fps.view(np.uint64))
                yield pa.RecordBatch.from_arrays([pa.array(keys), pa.array(fps[rows])], ["key", "fp"])

    rows = distinct.select("fp").mapInArrow(keyed, "key long, fp long")
    # crowded keys only: their number of blocks. Most keys have one fingerprint and never appear here.
    folder = common.settled(rows, "golay-keys")
    crowded = folder.groupBy("key").agg(F.count("*").alias("n")).where(F.col("n") > CELL).select("key", F.ceil(F.col("n") / CELL).cast("int").alias("blocks"))
    dealt = folder.join(crowded, "key", "left").withColumn("blocks", F.coalesce("blocks", F.lit(1)))
    block = F.pmod(F.xxhash64("fp"), F.col("blocks")).cast("int")
    cells = F.transform(F.sequence(F.lit(0), F.col("blocks") - 1), lambda other: F.struct(F.least(other, F.col("block")).alias("i"), F.greatest(other, F.col("block")).alias("j")))
    cut = dealt.withColumn("block", block).select("key", "fp", F.explode(cells).alias("cell")).select("key", "cell.i", "cell.j", "fp")
    lined = cut.repartition(F.col("key"), F.col("i"), F.col("j")).sortWithinPartitions("key", "i", "j")

    def verified(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rest = None
        for batch in batches:
            now = [np.asarray(batch.column(k).to_numpy(zero_copy_only=False)).astype(np.int64) for k in range(4)]
            if rest is not None:
                now = [np.concatenate(x) for x in zip(rest, now, strict=True)]
            same = (now[0][1:] == now[0][:-1]) & (now[1][1:] == now[1][:-1]) & (now[2][1:] == now[2][:-1])
            starts = np.concatenate([[0], np.flatnonzero(~same) + 1])
            rest = [x[starts[-1] :] for x in now]
            yield _found(now[3], starts)
        if rest is not None:
            yield _found(rest[3], np.asarray([0, len(rest[3])]))

    def _found(fps: np.ndarray, starts: np.ndarray) -> pa.RecordBatch:
        sizes = np.diff(starts)
        u, v = [], []
        twos = starts[:-1][sizes == 2]
        near = np.bitwise_count((fps[twos] ^ fps[twos + 1]).view(np.uint64)) <= radius if len(twos) else np.zeros(0, bool)
        u.append(fps[twos[near]])
        v.append(fps[twos[near] + 1])
        for at, n in zip(starts[:-1][sizes > 2].tolist(), sizes[sizes > 2].tolist(), strict=True):
            own = np.unique(fps[at : at + n])
            if got := walk(own.view(np.uint64), radius):
                x, y = np.asarray(got).T
                u.append(own[x])
                v.append(own[y])
        u, v = np.concatenate(u), np.concatenate(v)
        return pa.RecordBatch.from_arrays([pa.array(np.minimum(u, v)), pa.array(np.maximum(u, v))], ["u", "v"])

    return lined.mapInArrow(verified, "u long, v long").where("u <> v").distinct()


def components(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """``node, root``: the smallest node of each component, for every node that has a link.

    Large-star and small-star rounds in turn; each is an aggregate and a join on written tables, and
    the number of rounds grows with the logarithm of the longest path.
    """
    now = common.settled(edges.select("u", "v").where("u <> v").select(F.least("u", "v").alias("v"), F.greatest("u", "v").alias("u")).distinct(), "edges")
    seen = None
    for _ in range(most_rounds):
        both = now.select("u", "v").unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        smallest = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(smallest, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(smallest.select("u", F.col("m").alias("v")))
        now = common.settled(small.where("u <> v").distinct(), "edges")
        mark = now.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if mark == seen:
            break
        seen = mark
    else:
        raise RuntimeError(f"components did not settle in {most_rounds} rounds")
    return now.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(now.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())


def near_duplicates(docs: DataFrame, width: int = 3, radius: int = 3, seed: int = 42) -> DataFrame:
    """``doc_id, fp, component_id``: the smallest doc_id that links reach, for every document."""
    prints = common.settled(fingerprints(docs, width, seed), "fingerprints")
    joined, best = _grouped(prints, "doc_id", radius)
    named = joined.join(best.withColumnRenamed("least", "component_id"), "root").select("fp", "component_id")
    return prints.join(named, "fp").select("doc_id", "fp", "component_id")


def _grouped(prints: DataFrame, value: str, radius: int) -> tuple[DataFrame, DataFrame]:
    """``fp, first, root`` of every distinct fingerprint, and ``root, least``: the least ``value`` of each component."""
    groups = common.settled(prints.groupBy("fp").agg(F.min(value).alias("first")), "distinct")
    roots = components(links(groups, radius))
    joined = groups.join(roots, groups.fp == roots.node, "left").select("fp", "first", F.coalesce("root", "fp").alias("root"))
    return joined, joined.groupBy("root").agg(F.min("first").alias("least"))


def survivors(docs: DataFrame, width: int = 3, radius: int = 3, seed: int = 42) -> DataFrame:
    """One row of each component, with all its columns: the smallest doc_id, of its texts there the one of the smallest hash.

    Components are told apart by their fingerprints, so that rows of one doc_id in several of them stay in each.
    """
    prints = fingerprints(docs, width, seed, hashed=True)
    _, best = _grouped(prints.select("fp", F.struct("doc_id", "text_hash").alias("row")), "row", radius)
    chosen = best.select("least.doc_id", F.col("least.text_hash").alias("__h"))
    order = Window.partitionBy("doc_id", "__h").orderBy("text")
    found = docs.withColumn("__h", F.xxhash64("text")).join(chosen, ["doc_id", "__h"], "left_semi")
    return found.withColumn("__row", F.row_number().over(order)).where("__row = 1").select(*docs.columns)


def fingerprint_hex(fp: Column) -> Column:
    return F.lower(F.lpad(F.hex(fp), 16, "0"))
