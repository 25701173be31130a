"""The experiment workloads, re-expressed: each gives rows of measurements.

Runs are walked by the engines, never by the driver: repeats over seeds and settings are one job with a task a run
(``descent.walked``); timed runs use the engines whose workers run side by side (``mailbox``, streamed one-shot), on
samples that are placed before the clock starts. Errors are means over all points.
"""

from __future__ import annotations

import time
from collections.abc import Iterable
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gossamer.config import DescentConfig
from gossamer.operators import codebook, descent, draws, mailbox, metrics
from gossamer.operators.descent import as_array, batch_descent, gossip_sgd, initial_state, oneshot_sgd
from gossamer.sources import points as sets
from gossamer.sources.shared import settled, shared_dir

BASE = DescentConfig(k=10, b=50, steps=20, workers=4, eps=1.0)
WIDE = DescentConfig(k=10, b=500, steps=50, workers=4, eps=1.0)  # mini-batches as in the published runs
RUNS = "method string, workers int, k int, b int, seed int, touched long, secs double, error double, sent long, received long, good long, final string"


def single(cfg: DescentConfig) -> DescentConfig:
    """The same samples touched one at a time."""
    return cfg.with_(b=1, steps=cfg.steps * cfg.b, eps=cfg.eps / cfg.b)


def of_method(cfg: DescentConfig, method: str) -> DescentConfig:
    """Settings of gossip, silent, oneshot, oneshot_first or minibatch runs that touch the same samples."""
    if method in ("oneshot", "oneshot_first"):
        return single(cfg).with_(comm="silent", final="average" if method == "oneshot" else "first")
    return cfg.with_(comm="silent") if method == "silent" else cfg


def placed_mix(spark: SparkSession, dims: int, m: int, k: int, **more) -> DataFrame:
    """The planted mixture, written once."""
    return settled(sets.mix(spark, dims, m, k, tasks=4 * spark.sparkContext.defaultParallelism, **more), "mix")


# --- single runs ------------------------------------------------------------------------------------------------


def one_run(points: DataFrame, cfg: DescentConfig, method: str = "gossip", engine: str = "auto") -> dict:
    """Seconds and error of one run; the samples are placed before the clock starts. ``oneshot_first``: one-shot without its average."""
    w0 = initial_state(points, cfg)
    if method == "batch":
        secs, out = metrics.timed(points, lambda p: batch_descent(p, cfg, w0))
    elif method in ("oneshot", "oneshot_first"):
        secs, out = metrics.timed(points, lambda p: oneshot_sgd(p, cfg, w0, final="first" if method == "oneshot_first" else "average"))
    else:
        secs, out = metrics.timed(points, lambda p: gossip_sgd(p, cfg.with_(comm="silent" if method == "silent" else cfg.comm), w0, engine))
    w = as_array(out.state())
    counts = out.states.agg(F.sum("sent"), F.sum("received"), F.sum("good")).first()
    m = points.count() if method == "batch" else 0
    return {"method": method, "workers": cfg.workers, "k": cfg.k, "b": cfg.b, "seed": cfg.seed, "touched": metrics.touched(method, cfg.steps, m, cfg.workers, cfg.b), "secs": secs, "error": descent.error_of(points, w.tolist()), "sent": counts[0], "received": counts[1], "good": counts[2], "final": out.config.final}


def _frame(spark: SparkSession, rows: list[dict]) -> DataFrame:
    return spark.createDataFrame(rows, RUNS)


def side_by_side(points: DataFrame, cfg: DescentConfig, method: str, w0: list, m: int | None = None) -> dict:
    """Seconds of a run whose workers run at the same time, from placed samples to the result; ``with_errors`` turns its state into an error.

    Batch has ``workers`` tasks, which read the table. ``m``: the number of samples, where ``points`` are only those that a run draws.
    """
    spark = points.sparkSession
    own = of_method(cfg, method) if method != "batch" else cfg
    if method == "batch":
        placed = points.coalesce(cfg.workers)
        run = lambda: batch_descent(placed, own, w0)
        touched = cfg.steps * (points.count() if m is None else m)
    else:
        if own.workers < 2:
            own = own.with_(comm="silent")
        placed = mailbox.lined_up(draws.minibatches(points, own, m), own).persist()
        slots = spark.sparkContext.defaultParallelism >= own.workers and shared_dir(spark).startswith(("file:", "/"))
        if own.b == 1:
            run = lambda: descent.RunResult(_streamed(placed, own, w0), own)
        elif slots:
            run = lambda: descent.RunResult(mailbox.mailbox_run(placed, own, w0, True), own)
        else:
            run = lambda: descent.RunResult(descent.latest(descent.supersteps(placed, own, w0)[0], spark, own), own)
        touched = placed.count()
    began = time.time()
    out = run()
    states = settled(out.states, "states") if method != "batch" else out.states
    w = as_array(descent.RunResult(states, out.config).state())
    secs = time.time() - began
    if method != "batch":
        placed.unpersist()
    counts = states.agg(F.sum("sent"), F.sum("received"), F.sum("good")).first()
    return {"method": method, "workers": cfg.workers, "k": cfg.k, "b": cfg.b, "seed": cfg.seed, "touched": touched, "secs": secs, "error": w, "sent": counts[0], "received": counts[1], "good": counts[2], "final": out.config.final}


def with_errors(points: DataFrame, rows: list[dict]) -> list[dict]:
    """The states of ``side_by_side`` become errors over all points, in one pass."""
    return [{**r, "error": e} for r, e in zip(rows, descent.errors_of(points, [r["error"] for r in rows]), strict=True)]


def all_drawn(points: DataFrame, cfg: DescentConfig, most: int, m: int) -> DataFrame:
    """What runs of this seed draw that touch at most ``most`` of ``m`` samples: cut once for all of them, or the whole table."""
    return points if most >= m else settled(draws.foremost(points.select("sample_id", "x"), cfg.seed, most), "foremost")


def _streamed(placed: DataFrame, cfg: DescentConfig, w0: list) -> DataFrame:
    """One-shot workers over placed samples: a task each, batches streamed."""
    return descent.streamed(placed.select("worker", "x"), cfg, w0)


def rounds_for(touched: int, cfg: DescentConfig) -> DescentConfig:
    return cfg.with_(steps=max(1, round(touched / (cfg.workers * cfg.b))))


def strong_scaling(spark: SparkSession, points: DataFrame, touched: int | Iterable[int] = 4000, workers=(2, 4, 8), cfg: DescentConfig = BASE, methods=("gossip", "oneshot", "batch"), name: str = "") -> DataFrame:
    """Fixed samples touched, more workers; speed-up and efficiency by method. Batch takes whole passes: one at least."""
    m, w0, out = points.count(), initial_state(points, cfg), []
    plans = {total: [(rounds_for(total, cfg.with_(workers=n)) if method != "batch" else cfg.with_(workers=n, steps=max(1, round(total / m))), method) for n in workers for method in methods] for total in ([touched] if isinstance(touched, int) else touched)}
    drawn = all_drawn(points, cfg, max([c.workers * c.b * c.steps for runs in plans.values() for c, method in runs if method != "batch"], default=m), m)
    for total, runs in plans.items():
        rows = with_errors(points, [side_by_side(points if method == "batch" else drawn, c, method, w0, m) for c, method in runs])
        out.append(metrics.scaling_table(_frame(spark, rows)).withColumn("budget", F.lit(total).cast("long")))
    return reduce(DataFrame.unionByName, out).withColumn("points", F.lit(name))


def k_sweep(spark: SparkSession, points: DataFrame, ks=(10, 30, 100), cfg: DescentConfig = BASE) -> DataFrame:
    """Seconds over ln k; both methods touch the same number of samples."""
    return metrics.k_scaling(_frame(spark, [one_run(points, each.with_(k=k), m) for k in ks for m, each in (("gossip", cfg), ("oneshot", single(cfg)))]))


# --- many runs in one job -----------------------------------------------------------------------------------------


def walk_all(points: DataFrame, runs: dict[str, DescentConfig], marks: int = 0) -> DataFrame:
    """``descent.walked`` for named settings, with ``marks`` states along each run (0: the last only).

    Runs of equal draws share them; each run starts from its own seed's initial state.
    """
    m, starts, keyed = points.count(), {}, {}
    for name, cfg in runs.items():
        cfg.validate(m)
        starts.setdefault((cfg.seed, cfg.k, cfg.init), cfg)
        keyed.setdefault((cfg.seed, cfg.b, cfg.steps, cfg.workers, cfg.draw, cfg.remainder), []).append(name)
    w0 = {key: initial_state(points, cfg) for key, cfg in starts.items()}
    parts = [draws.minibatches(points, runs[names[0]], m).withColumn("run", F.explode(F.array(*map(F.lit, names)))) for names in keyed.values()]
    drawn = settled(reduce(DataFrame.unionByName, [p.select("run", "worker", "round", "slot", "x") for p in parts]), "drawn", "run")
    rows = {name: (cfg, w0[cfg.seed, cfg.k, cfg.init]) for name, cfg in runs.items()}
    if not marks:
        return settled(descent.walked(drawn, rows), "runs")
    # a run with more rounds shows as many states: marks lie at equal shares of each run
    groups: dict[int, list[str]] = {}
    for name, cfg in runs.items():
        groups.setdefault(max(1, cfg.steps // marks), []).append(name)
    return settled(reduce(DataFrame.unionByName, [descent.walked(drawn.where(F.col("run").isin(names)), {n: rows[n] for n in names}, every) for every, names in groups.items()]), "runs")


def errors_along(points: DataFrame, states: DataFrame, runs: dict[str, DescentConfig], truth: DataFrame | None = None) -> list[tuple]:
    """``run_id, round, touched, secs, error`` (and the centre error) of each kept round, in one pass over the points."""
    first_only = [n for n, cfg in runs.items() if cfg.final == "first"]
    kept = states.where(~F.col("run").isin(first_only) | (F.col("worker") == 0)).select("run", "round", "secs", "w").orderBy("run", "round", "worker").collect()  # marks * workers * k * d values a run
    at: dict[tuple, list] = {}
    for r in kept:
        at.setdefault((r.run, r["round"], r.secs), []).append(r.w)
    shown = [np.mean(np.asarray(ws), axis=0) for ws in at.values()]
    rows = [(run, t - 1, t * runs[run].b * runs[run].workers, secs, e) for (run, t, secs), e in zip(at, descent.errors_of(points, shown), strict=True)]
    if truth is None:
        return rows
    mu = np.asarray([r.mu for r in truth.orderBy("center").collect()])
    return [(*r, metrics.center_error(mu, w)) for r, w in zip(rows, shown, strict=True)]


def convergence(points: DataFrame, cfg: DescentConfig, methods=("gossip", "silent", "oneshot"), truth: DataFrame | None = None, seeds: Iterable[int] | None = None, marks: int = 20) -> list[tuple]:
    """``run_id, round, touched, secs, error`` along each run, named by method and seed. With ``truth`` the centre error follows."""
    runs = {f"{m}-{s}": of_method(cfg.with_(seed=s), m) for s in (seeds or [cfg.seed]) for m in methods}
    return errors_along(points, walk_all(points, runs, marks), runs, truth)


def trace_frame(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    """The rows of ``convergence``; ``center`` is null where no truth was given."""
    return spark.createDataFrame([(*r, None)[:6] for r in rows], "run_id string, round int, touched long, secs double, error double, center double")


def repeats(spark: SparkSession, points: DataFrame, seeds=range(10), cfg: DescentConfig = BASE, truth: DataFrame | None = None, methods=("gossip", "silent", "oneshot"), patience: int = 3) -> DataFrame:
    """Errors of every method at convergence over seeds: mean, variance, range; the mean centre error where the truth is known."""
    frame = trace_frame(spark, convergence(points, cfg, methods, truth, seeds))
    center = frame.groupBy("run_id").agg(F.max_by("center", "round").alias("center")).groupBy(F.split("run_id", "-")[0].alias("method")).agg(F.avg("center").alias("center_mean"))
    last = metrics.final_error(frame, patience).withColumn("method", F.split("run_id", "-")[0])
    return metrics.summarise(last, "method").join(center, "method")


def crossing(spark: SparkSession, rows: list[tuple], base: str) -> DataFrame:
    """Samples and seconds until each run reaches the worst of the runs' last errors, and how many times fewer than ``base``."""
    frame = trace_frame(spark, rows)
    level = max(r.error for r in metrics.final_error(frame).collect())
    return metrics.speedup_to_error(frame, level * (1 + 1e-12), base).withColumn("level", F.lit(level))


def variants(spark: SparkSession, points: DataFrame, cfg: DescentConfig, changes: dict[str, dict], seeds: Iterable[int]) -> DataFrame:
    """Mean error and messages of each variant over seeds."""
    runs = {f"{name}-{s}": cfg.with_(seed=s, **v) for name, v in changes.items() for s in seeds}
    states = walk_all(points, runs)
    counts = states.groupBy("run").agg(F.avg("sent").alias("sent"), F.avg("received").alias("received"), F.avg("good").alias("good"))
    errors = spark.createDataFrame([(r[0], r[2], r[4]) for r in errors_along(points, states, runs)], "run string, touched long, error double")
    rows = errors.join(counts, "run").withColumn("variant", F.split("run", "-")[0])
    means = [F.avg(c).alias(c) for c in ("touched", "error", "sent", "received", "good")]
    return rows.groupBy("variant").agg(F.count("*").alias("repeats"), *means, (F.stddev_samp("error") / F.sqrt(F.count("*"))).alias("standard_error"))


# --- smaller forms, with parameters ---------------------------------------------------------------------------------


def overhead(spark: SparkSession, points: DataFrame, bs=(50, 200, 500), touched: int = 4000, cfg: DescentConfig = BASE) -> DataFrame:
    """Seconds of gossip over silent and one-shot runs by the frequency of messages, 1 / b."""
    w0 = initial_state(points, cfg)
    rows = with_errors(points, [side_by_side(points, rounds_for(touched, cfg.with_(b=b)), m, w0) for b in bs for m in ("gossip", "silent", "oneshot")])
    dims, out = len(w0[0]), metrics.comm_overhead(_frame(spark, rows))
    sent = spark.createDataFrame([(r["b"], r["sent"] * cfg.k * dims * 8) for r in rows if r["method"] == "gossip"], "b int, bytes long")
    return out.join(sent, "b")


def message_sweep(spark: SparkSession, points: DataFrame, workers=(2, 4, 8, 16), cfg: DescentConfig = BASE, fixed: str = "steps", touched: int = 8000) -> DataFrame:
    """Messages sent, received and counted, a worker and a mini-batch, by the number of workers."""
    runs = {f"{n}": cfg.with_(workers=n, steps=cfg.steps if fixed == "steps" else max(1, touched // (n * cfg.b))) for n in workers}
    states = walk_all(points, runs)
    out = [metrics.message_rates(states.where(F.col("run") == name), c.steps).withColumn("workers", F.lit(c.workers)).withColumn("fixed", F.lit(fixed)) for name, c in runs.items()]
    return reduce(DataFrame.unionByName, out)


def final_step(spark: SparkSession, points: DataFrame, cfg: DescentConfig = BASE, seeds: Iterable[int] = (7,)) -> DataFrame:
    """One worker's state against the average: error and seconds, by seed."""
    rows = []
    for s in seeds:
        own = cfg.with_(seed=s)
        w0, placed = initial_state(points, own), draws.minibatches(points, own).persist()
        placed.count()
        for final in ("first", "average"):
            began = time.time()
            result = descent.RunResult(settled(descent.folded(placed, own, w0), "states"), own.with_(final=final))
            w = as_array(result.state())
            rows.append({"method": "gossip", "workers": own.workers, "k": own.k, "b": own.b, "seed": s, "touched": own.workers * own.b * own.steps, "secs": time.time() - began, "error": w, "sent": 0, "received": 0, "good": 0, "final": final})
        placed.unpersist()
    for r, e in zip(rows, descent.errors_of(points, [r["error"] for r in rows]), strict=True):
        r["error"] = e
    return metrics.compare_final(_frame(spark, rows).withColumn("run_id", F.col("seed").cast("string")))


ABLATION = {"full": {}, "no_window": {"window": False}, "half_blocks": {"block_frac": 0.5}, "tenth_blocks": {"block_frac": 0.1}, "two_buffers": {"buffers": 2, "fanout": 2}, "four_buffers": {"buffers": 4, "fanout": 3}, "torn": {"race": "torn", "fanout": 2, "block_frac": 0.5}, "lossless": {"race": "none", "fanout": 2}, "silent": {"comm": "silent"}, "rare": {"comm_every": 4}, "sync": {"comm": "sync"}, "delayed": {"max_age": 3}}


def ablation(spark: SparkSession, points: DataFrame, cfg: DescentConfig = BASE, seeds: Iterable[int] = (7,)) -> DataFrame:
    """Window, partial states, buffers and races: error and messages of each variant."""
    return variants(spark, points, cfg, ABLATION, seeds)


def overlap(spark: SparkSession, m: int = 4000, cfg: DescentConfig = BASE, seeds: Iterable[int] = (7,)) -> DataFrame:
    """Centre error by the spread of the noise and the least distance of centres."""
    rows = []
    for name, sigma, apart in (("easy", 0.5, 8.0), ("medium", 1.0, 4.0), ("hard", 3.0, 0.0)):
        points, truth = placed_mix(spark, 10, m, cfg.k, sigma=sigma, min_dist=apart), sets.truth(spark, 10, cfg.k, sigma=sigma, min_dist=apart)
        runs = {f"gossip-{s}": cfg.with_(seed=s) for s in seeds}
        states = walk_all(points, runs).where("worker = 0").select("run", "w").collect()
        mu = np.asarray([r.mu for r in truth.orderBy("center").collect()])
        rows += [(name, r.run, *[metrics.center_error(mu, np.asarray(r.w), match) for match in ("nearest", "greedy", "hungarian")]) for r in states]
    frame = spark.createDataFrame(rows, "difficulty string, run string, nearest double, greedy double, hungarian double")
    return frame.groupBy("difficulty").agg(F.count("*").alias("repeats"), *[F.avg(c).alias(c) for c in ("nearest", "greedy", "hungarian")])


# --- the workloads at the survey's sizes -------------------------------------------------------------------------------

SEEDS = range(10)


def w1_strong_scaling(spark, sf_dir):
    """Mixture of 1,000,000 samples, k = 10, 100,000 and 1,000,000 samples touched by 1, 2 and 4 workers; line items, 100,000."""
    parts = [(placed_mix(spark, 10, 1_000_000, 10), "mix", (100_000, 1_000_000)), (settled(sets.line4(spark, sf_dir), "line4"), "line4", (100_000,))]
    return reduce(DataFrame.unionByName, [strong_scaling(spark, p, budgets, (1, 2, 4), WIDE, name=n) for p, n, budgets in parts])


def w2_wide_scaling(spark, sf_dir):
    """Documents (128 features) and embeddings; 100,000 samples touched, k = 10 and 100; line items with k = 1000.

    Batch descent, whose passes are many where tables are small, is left to ``w1_strong_scaling`` and ``w3_k_scaling``.
    """
    parts = [(settled(sets.doc128(spark, sf_dir), "doc128"), "doc128", (10, 100)), (settled(sets.emb64(spark, sf_dir), "emb64"), "emb64", (10, 100)), (sets.line4(spark, sf_dir), "line4", (1000,))]
    return reduce(DataFrame.unionByName, [strong_scaling(spark, p, 100_000, (1, 2, 4), WIDE.with_(k=k, b=50), ("gossip", "oneshot"), n) for p, n, ks in parts for k in ks])


def w3_k_scaling(spark, sf_dir):
    """Line items, 100,000 samples touched, k = 10 to 1000: seconds over ln k."""
    points, ks, rows = sets.line4(spark, sf_dir), (10, 30, 100, 300, 1000), []
    base, m = rounds_for(100_000, WIDE), points.count()
    first = initial_state(points, base.with_(k=ks[-1]))  # fewer prototypes are the first of these
    drawn = all_drawn(points, base, base.workers * base.b * base.steps, m)
    for k in ks:
        cfg = base.with_(k=k)
        rows += [side_by_side(points if method == "batch" else drawn, cfg if method != "batch" else cfg.with_(steps=1), method, first[:k], m) for method in ("gossip", "oneshot", "batch")]
    rows = with_errors(points, rows)
    runs = _frame(spark, rows)
    return runs.select("method", "k", "secs", "error").join(metrics.k_scaling(runs), "method")


def w4_convergence(spark, sf_dir):
    """k = 100, b = 500, 16 workers, 200,000 samples of ten dimensions: samples and seconds to a fixed error."""
    points = placed_mix(spark, 10, 200_000, 100)
    cfg = WIDE.with_(k=100, workers=16)
    rows = convergence(points, cfg, ("gossip", "silent", "oneshot"))
    w0 = initial_state(points, cfg)
    passes = batch_descent(points, cfg.with_(steps=10), w0)
    rows += [("batch-7", t, touched, secs, error) for t, touched, secs, error, *_ in passes.trace]
    return crossing(spark, rows, "oneshot-7")


def w5_repeats(spark, sf_dir):
    """Ten repeats on 100,000 samples: converged error, its variance, and the centre error."""
    return repeats(spark, placed_mix(spark, 10, 100_000, 10), SEEDS, WIDE, sets.truth(spark, 10, 10))


def w6_overhead(spark, sf_dir):
    """Seconds of gossip over silent and one-shot runs, b = 50 to 10,000."""
    return overhead(spark, placed_mix(spark, 10, 100_000, 10), (50, 100, 500, 1000, 2000, 10_000), 80_000, WIDE)


def w7_messages(spark, sf_dir):
    """Messages a worker with 2 to 32 workers, rounds fixed and samples fixed."""
    points = placed_mix(spark, 10, 100_000, 10)
    return reduce(DataFrame.unionByName, [message_sweep(spark, points, (2, 4, 8, 16, 32), BASE, fixed, 80_000) for fixed in ("steps", "touched")])


def w8_rare_messages(spark, sf_dir):
    """One message in 500 samples against one in 100,000, by mini-batch size and by keeping 500; messages that never leave."""
    points = placed_mix(spark, 10, 200_000, 100)
    cfg = WIDE.with_(k=100, workers=2, steps=400)
    runs = {"often-7": cfg, "rare-7": cfg.with_(comm_every=200), "large-7": cfg.with_(b=100_000, steps=2), "never-7": cfg.with_(comm_every=401), "silent-7": cfg.with_(comm="silent"), "oneshot-7": of_method(cfg, "oneshot")}
    states = walk_all(points, runs, 20)
    sent = states.groupBy("run").agg(F.max("sent").alias("sent"), F.max("received").alias("received"), F.max("good").alias("good"))
    frame = trace_frame(spark, errors_along(points, states, runs)).withColumnRenamed("run_id", "run")
    return frame.join(sent, "run").select("run", "round", "touched", "error", "sent", "received", "good")


def w9_silent(spark, sf_dir):
    """Gossip against silent and one-shot runs over ten seeds: mean error along the way."""
    rows = convergence(placed_mix(spark, 10, 100_000, 10), WIDE, seeds=SEEDS, marks=10)
    return trace_frame(spark, rows).groupBy(F.split("run_id", "-")[0].alias("method"), "touched").agg(F.count("*").alias("repeats"), F.avg("error").alias("mean"), (F.stddev_samp("error") / F.sqrt(F.count("*"))).alias("standard_error"), F.avg("secs").alias("secs"))


def w10_final(spark, sf_dir):
    """First worker against average over ten seeds: errors and seconds."""
    return final_step(spark, placed_mix(spark, 10, 100_000, 10), WIDE, SEEDS)


def w12_codebook(spark, sf_dir):
    """A codebook of 100 entries on the documents; histograms of sources and languages."""
    points = settled(sets.doc128(spark, sf_dir), "doc128")
    w = as_array(gossip_sgd(points, BASE.with_(k=100)).state()).tolist()
    docs = sets.table(spark, sf_dir, "documents").select(F.col("doc_id").cast("string").alias("sample_id"), "lang", "source")
    groups = docs.select("sample_id", F.concat(F.lit("lang:"), F.coalesce("lang", F.lit("")))).union(docs.select("sample_id", F.concat(F.lit("source:"), F.coalesce("source", F.lit(""))))).toDF("sample_id", "object")
    return codebook.histogram(points, w, groups)


def w13_overlap(spark, sf_dir):
    """Centre error by difficulty over ten seeds on 100,000 samples."""
    return overlap(spark, 100_000, WIDE, SEEDS)


def w14_ablation(spark, sf_dir):
    """Window, partial states, buffers, races and ages over ten seeds on 100,000 samples."""
    return ablation(spark, placed_mix(spark, 10, 100_000, 10), BASE.with_(steps=100), SEEDS)


WORKLOADS = {f.__name__: f for f in (w1_strong_scaling, w2_wide_scaling, w3_k_scaling, w4_convergence, w5_repeats, w6_overhead, w7_messages, w8_rare_messages, w9_silent, w10_final, w12_codebook, w13_overlap, w14_ablation)}
