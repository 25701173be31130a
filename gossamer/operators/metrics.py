"""Cost and accuracy measures."""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gossamer.config import DescentConfig
from gossamer.functions.arrays import sqdist


def touched(method: str, steps: int, m: int, workers: int, b: int) -> int:
    """Samples touched: every sample each pass; a sample a worker and step; a mini-batch a worker and round."""
    return {"batch": steps * m, "oneshot": steps * workers, "oneshot_first": steps * workers, "online": steps, "minibatch": steps * b, "gossip": steps * b * workers, "silent": steps * b * workers}[method]


def timed(points: DataFrame, run):
    """The seconds of a run on placed data, to its result (its average, if that is the result); placing is outside the measure."""
    held = points.persist()
    held.count()
    began = time.time()
    out = run(held)
    out.state().collect()  # k x d values
    secs = time.time() - began
    held.unpersist()
    return secs, out


def center_error(truth: np.ndarray, w: np.ndarray, match: str = "nearest") -> float:
    """Mean distance of planted centres to prototypes: the nearest each, matched one to one greedily, or with the least total."""
    d = np.sqrt(((truth[:, None] - w[None]) ** 2).sum(axis=2))
    if match == "nearest":
        return float(d.min(axis=1).mean())
    if match == "hungarian":
        return float(d[np.arange(len(truth)), least_matching(d)].mean())
    total, free, rest = 0.0, set(range(len(w))), set(range(len(truth)))
    for i, j in sorted(((i, j) for i in rest for j in free), key=lambda p: d[p]):
        if i in rest and j in free:
            total += d[i, j]
            rest.discard(i)
            free.discard(j)
    return float(total / len(truth))


def least_matching(cost: np.ndarray) -> np.ndarray:
    """The column of each row so that the total cost is least: shortest augmenting paths with potentials; any size, rows <= columns."""
    n, m = cost.shape
    if n > m:
        raise ValueError("more centres than prototypes")
    column_row = np.full(m + 1, -1)  # the last column is where a path starts
    by_row, by_column = np.zeros(n), np.zeros(m + 1)
    for row in range(n):
        column_row[m] = row
        at, reach = m, np.full(m, np.inf)
        came, done = np.full(m, m), np.zeros(m + 1, bool)
        while column_row[at] >= 0:
            done[at] = True
            i = column_row[at]
            slack = cost[i] - by_row[i] - by_column[:m]
            nearer = ~done[:m] & (slack < reach)
            reach[nearer], came[nearer] = slack[nearer], at
            following = int(np.where(done[:m], np.inf, reach).argmin())
            step = reach[following]
            by_row[column_row[done]] += step
            by_column[done] -= step
            reach[~done[:m]] -= step
            at = following
        while at != m:
            column_row[at], at = column_row[came[at]], came[at]
    out = np.empty(n, np.int64)
    out[column_row[:m][column_row[:m] >= 0]] = np.flatnonzero(column_row[:m] >= 0)
    return out


def center_error_frame(truth: DataFrame, state: DataFrame) -> DataFrame:
    """``center, distance``: from each planted centre to the nearest of k prototypes ``(block, w)``."""
    near = truth.join(F.broadcast(state), F.lit(True)).withColumn("d", F.sqrt(sqdist("mu", "w")))
    return near.groupBy("center").agg(F.min("d").alias("distance"))


def converged_at(trace: DataFrame, patience: int, tol: float = 0.0) -> DataFrame:
    """``run_id, round``: the first round after which the error has not improved for ``patience`` rounds."""
    own = Window.partitionBy("run_id").orderBy("round")
    best = trace.withColumn("best", F.min("error").over(own.rowsBetween(Window.unboundedPreceding, 0))).withColumn("before", F.min("error").over(own.rowsBetween(Window.unboundedPreceding, -patience)))
    return best.where(F.col("before").isNotNull() & (F.col("best") >= F.col("before") - tol)).groupBy("run_id").agg(F.min("round").alias("round"))


def time_to_error(trace: DataFrame, level: float) -> DataFrame:
    """``run_id, touched, secs`` where the error first reaches ``level``."""
    return trace.where(F.col("error") <= level).groupBy("run_id").agg(F.min("touched").alias("touched"), F.min("secs").alias("secs"))


def speedup_to_error(trace: DataFrame, level: float, base: str) -> DataFrame:
    """``run_id, touched, secs, fewer, faster``: how many times fewer samples and seconds than run ``base`` to an error level."""
    reached = time_to_error(trace, level)
    of = reached.where(F.col("run_id") == base).select(F.col("touched").alias("base_touched"), F.col("secs").alias("base_secs"))
    both = reached.join(F.broadcast(of), F.lit(True))  # one row
    return both.select("run_id", "touched", "secs", (F.col("base_touched") / F.col("touched")).alias("fewer"), (F.col("base_secs") / F.col("secs")).alias("faster"))


def final_error(trace: DataFrame, patience: int | None = None) -> DataFrame:
    """``run_id, error``: of the round in which a run has converged by ``patience``, else of its last round."""
    last = trace.groupBy("run_id").agg(F.max_by("error", "round").alias("error"))
    if patience is None:
        return last
    at = trace.join(converged_at(trace, patience), ["run_id", "round"]).select("run_id", F.col("error").alias("settled"))
    return last.join(at, "run_id", "left").select("run_id", F.coalesce("settled", "error").alias("error"))


def summarise(runs: DataFrame, *by: str) -> DataFrame:
    """Mean, sample variance and deviation, least and largest error over repeats."""
    e = "error"
    return runs.groupBy(*by).agg(F.count("*").alias("repeats"), F.avg(e).alias("mean"), F.var_samp(e).alias("variance"), F.stddev_samp(e).alias("deviation"), F.min(e).alias("least"), F.max(e).alias("largest"))


def scaling_table(runs: DataFrame) -> DataFrame:
    """Runs ``(method, workers, secs)``: speed-up and efficiency against the fewest workers."""
    own = Window.partitionBy("method").orderBy("workers")
    base = runs.withColumn("secs0", F.first("secs").over(own)).withColumn("workers0", F.first("workers").over(own))
    return base.withColumn("speedup", F.col("secs0") / F.col("secs")).withColumn("efficiency", F.col("speedup") * F.col("workers0") / F.col("workers")).drop("secs0", "workers0")


def k_scaling(runs: DataFrame) -> DataFrame:
    """Runs ``(method, k, secs)``: seconds for each unit of ln k."""
    return runs.groupBy("method").agg(F.regr_slope("secs", F.log("k")).alias("slope"), F.regr_r2("secs", F.log("k")).alias("r2"))


def comm_overhead(runs: DataFrame) -> DataFrame:
    """Runs ``(method, b, secs)``: by how much gossip takes longer than silent and, where they ran, one-shot runs, by mini-batch size."""
    of = lambda m: F.first(F.when(F.col("method") == m, F.col("secs")), ignorenulls=True).alias(f"{m}_secs")
    wide = runs.groupBy("b").agg(*map(of, ("gossip", "silent", "oneshot"))).where("gossip_secs is not null and silent_secs is not null")
    return wide.select("b", F.col("gossip_secs").alias("secs"), "silent_secs", "oneshot_secs", (F.col("gossip_secs") / F.col("silent_secs") - 1).alias("overhead"), (F.col("gossip_secs") / F.col("oneshot_secs") - 1).alias("overhead_oneshot"))


def compare_final(runs: DataFrame) -> DataFrame:
    """Runs ``(run_id, final, error, secs)``: first worker against average."""
    a, b = (runs.where(F.col("final") == f).select("run_id", F.col("error").alias(f"{f}_error"), F.col("secs").alias(f"{f}_secs")) for f in ("first", "average"))
    return a.join(b, "run_id")


def message_rates(states: DataFrame, steps: int) -> DataFrame:
    """Means over workers: messages sent, received and counted, a worker and a mini-batch."""
    means = [F.avg(c) for c in ("sent", "received", "good")]
    return states.agg(*[m.alias(c) for m, c in zip(means, ("sent", "received", "good"), strict=True)], *[(m / steps).alias(f"{c}_rate") for m, c in zip(means, ("sent", "received", "good"), strict=True)])


def message_bytes(cfg: DescentConfig, dims: int) -> int:
    """Bytes that a run sends."""
    sent = cfg.workers * (cfg.steps // cfg.comm_every) * cfg.fanout * (cfg.comm != "silent")
    return sent * max(1, round(cfg.block_frac * cfg.k)) * dims * 8


def window_cost(cfg: DescentConfig, dims: int) -> float:
    """Multiplications of the window for each sample touched: two distances of the state's size a message, over b."""
    return 2.0 * cfg.fanout * cfg.k * dims / cfg.b


def worker_spread(states: DataFrame) -> DataFrame:
    """``block, dim, spread``: the deviation between workers."""
    from gossamer.operators.descent import long_form

    return long_form(states).groupBy("block", "dim").agg(F.stddev_pop("value").alias("spread"))


def partition_report(m: int, n: int) -> tuple[int, int]:
    """Samples a worker and samples left out."""
    return m // n, m % n
