"""Expressions on arrays and hashes; every fold runs from left to right, so that engines agree bit for bit."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _col(c) -> Column:
    return F.col(c) if isinstance(c, str) else c


def hash_hex(*key) -> Column:
    """md5 of the key's parts joined by colons."""
    return F.md5(F.concat_ws(":", *[_col(k).cast("string") for k in key]))


def hash_int(*key) -> Column:
    """The first 32 bits of the hash, as a long."""
    return F.conv(F.substring(hash_hex(*key), 1, 8), 16, 10).cast("long")


def total(values) -> Column:
    return F.aggregate(_col(values), F.lit(0.0), lambda s, v: s + v)


def sqdist(a, b) -> Column:
    return total(F.zip_with(_col(a), _col(b), lambda x, y: (x - y) * (x - y)))


def dot(a, b) -> Column:
    return total(F.zip_with(_col(a), _col(b), lambda x, y: x * y))


def norm(a) -> Column:
    return F.sqrt(dot(a, a))


# --- prototypes ---------------------------------------------------------------------------------------


def distances(x, w) -> Column:
    """Squared distance of a sample to every prototype."""
    return F.transform(_col(w), lambda c: sqdist(x, c))


def nearest(d2) -> Column:
    """0-based index of the least distance; the lowest of equal ones."""
    return (F.array_position(_col(d2), F.array_min(_col(d2))) - 1).cast("int")


def assign(x, w) -> Column:
    return nearest(distances(x, w))


# --- states: array<array<double>>, one inner array a block -----------------------------------------------


def state_sqdist(a, b) -> Column:
    """Over the blocks that both states have; null blocks are absent."""
    return sqdist(F.flatten(F.filter(F.zip_with(_col(a), _col(b), lambda x, y: F.when(y.isNotNull(), x)), lambda x: x.isNotNull())), F.flatten(F.filter(_col(b), lambda y: y.isNotNull())))


def moved(w, g, eps) -> Column:
    """w - eps * g"""
    return F.zip_with(_col(w), _col(g), lambda a, b: F.zip_with(a, b, lambda x, y: x - eps * y))


def window_accept(w, g, eps, e) -> Column:
    """Whether the own step would come strictly nearer to the received state; false for an empty buffer."""
    return F.coalesce(state_sqdist(moved(w, g, eps), e) < state_sqdist(w, e), F.lit(False)) & _col(e).isNotNull()


def blended(w, g, accepted) -> Column:
    """The modified step: the distance to the mean of the own state and the accepted ones, plus the own step."""

    def block(pair: Column) -> Column:
        own, of = pair["own"], pair["at"]
        peers = F.filter(F.transform(_col(accepted), lambda e: e[of]), lambda v: v.isNotNull())
        summed = F.aggregate(peers, own, lambda s, v: F.zip_with(s, v, lambda x, y: x + y))
        return F.zip_with(own, summed, lambda x, y: x - y / (F.size(peers) + 1))

    pairs = F.transform(_col(w), lambda own, at: F.struct(own.alias("own"), at.alias("at")))
    return F.zip_with(F.transform(pairs, block), _col(g), lambda a, b: F.zip_with(a, b, lambda x, y: x + y))


def register_functions(spark) -> None:
    """SQL names for the session: sqdist, kmeans_assign and window_accept."""
    d2 = "aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0.0D, (s, v) -> s + v)"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION sqdist(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN {d2}")
    each = d2.replace("zip_with(a, b", "zip_with(sample, c")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION kmeans_assign(sample ARRAY<DOUBLE>, w ARRAY<ARRAY<DOUBLE>>) RETURNS INT RETURN cast(array_position(transform(w, c -> {each}), array_min(transform(w, c -> {each}))) - 1 AS INT)")
    far = "aggregate(zip_with({}, e, (x, y) -> (x - y) * (x - y)), 0.0D, (s, v) -> s + v)"
    own = far.format("zip_with(w, g, (p, q) -> p - eps * q)")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION window_accept(w ARRAY<DOUBLE>, g ARRAY<DOUBLE>, eps DOUBLE, e ARRAY<DOUBLE>) RETURNS BOOLEAN RETURN coalesce({own} < {far.format('w')}, false)")
