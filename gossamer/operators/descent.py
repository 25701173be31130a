"""The methods: batch, online, mini-batch, one-shot and windowed gossip descent on prototypes.

Engines of the sequential and gossip methods, all on the same kernel:

* ``fold``: the samples that a run draws go to one task, which walks all rounds; for at most ``FOLD_MOST`` samples;
* ``superstep``: a job for each stretch of rounds; a worker's samples meet its state and its settled mail in a
  cogroup, states are written to the shared folder between jobs, which is also where a run can be continued;
* ``mailbox`` (``operators.mailbox``): one barrier job in which workers exchange states without waiting;
* ``auto``: ``fold`` for runs of at most ``FOLD_MOST`` samples, else ``superstep``.

A stop rule's samples and seconds end a run on every engine; its error level needs ``superstep`` and points to evaluate on.

Cases: samples are taken as they are (``sources.points.checked`` drops null, ragged and non-finite ones); repeated rows count;
extra columns are not read; an empty table has no initial state, which is an error.

What a run costs depends on the samples it touches, not on how many there are: the budget is cut by rank before any
sample moves.
"""

from __future__ import annotations

import time
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gossamer.config import DescentConfig
from gossamer.functions import kernel
from gossamer.functions.arrays import assign, distances, hash_hex
from gossamer.operators import draws, mail
from gossamer.sources.shared import settled

FOLD_MOST = 2_000_000
STATE = "worker int, w array<array<double>>, sent long, received long, good long"
TRACE = "round int, touched long, secs double, error double, sent long, received long, good long"


@dataclass
class RunResult:
    states: DataFrame  # STATE: one row a worker
    config: DescentConfig
    trace: list[tuple] = field(default_factory=list)
    w0: list | None = None

    def trace_frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.trace, TRACE)

    def state(self) -> DataFrame:
        """The result: the first worker's state, or the average, as ``block, dim, value``."""
        return first(self.states) if self.config.final == "first" else average(self.states)


# --- states -----------------------------------------------------------------------------------------------


def long_form(states: DataFrame) -> DataFrame:
    """``worker, block, dim, value``"""
    return states.select("worker", F.posexplode("w").alias("block", "v")).select("worker", "block", F.posexplode("v").alias("dim", "value"))


def nested_form(rows: DataFrame) -> DataFrame:
    """The way back: ``worker, w``."""
    inner = rows.groupBy("worker", "block").agg(F.transform(F.array_sort(F.collect_list(F.struct("dim", "value"))), lambda s: s["value"]).alias("v"))
    return inner.groupBy("worker").agg(F.transform(F.array_sort(F.collect_list(F.struct("block", "v"))), lambda s: s["v"]).alias("w"))


def first(states: DataFrame) -> DataFrame:
    return long_form(states.where("worker = 0")).drop("worker")


def average(states: DataFrame) -> DataFrame:
    return long_form(states).groupBy("block", "dim").agg(F.avg("value").alias("value"))


def as_array(state: DataFrame) -> np.ndarray:
    """k x d values of one state, on the driver."""
    rows = sorted((r.block, r.dim, r.value) for r in state.collect())
    return np.asarray([v for _, _, v in rows]).reshape(rows[-1][0] + 1, -1)


def initial_state(points: DataFrame, cfg: DescentConfig) -> list[list[float]]:
    """k prototypes for all workers: the first samples in hash order, samples drawn with replacement, hashed places inside the bounds, or zeros.

    A loss with a target starts at zeros, one weight a feature.
    """
    if cfg.loss != "prototypes":
        return [[0.0] * (_width(points) - 1)]
    if cfg.init == "first":
        rows = points.orderBy(hash_hex(F.lit(cfg.seed), F.lit("init"), "sample_id"), "sample_id").limit(cfg.k).select("x").collect()
        if not rows:
            raise ValueError("there are no samples")
        return [list(r.x) for r in rows]
    if cfg.init == "zeros":
        return [[0.0] * _width(points)] * cfg.k
    from hashlib import md5

    drawn = lambda *key: int(md5(":".join(map(str, key)).encode()).hexdigest()[:8], 16)
    if cfg.init == "sample":
        m = points.count()
        if not m:
            raise ValueError("there are no samples")
        places = [drawn(cfg.seed, "sample", c) % m for c in range(cfg.k)]
        ranked = draws.exact_rank(points.select("sample_id", "x"), hash_hex(F.lit(cfg.seed), F.lit("part"), "sample_id"), "sample_id", most=max(places) + 1)
        at = {r["rank"]: list(r.x) for r in ranked.where(F.col("rank").isin(places)).collect()}  # k rows
        return [at[p] for p in places]
    spans = points.select(F.posexplode("x").alias("dim", "v")).groupBy("dim").agg(F.min("v").alias("low"), F.max("v").alias("high")).orderBy("dim").collect()
    if not spans:
        raise ValueError("there are no samples")
    share = lambda c, j: drawn(cfg.seed, "bounds", c, j) / 2**32
    return [[s.low + (s.high - s.low) * share(c, s.dim) for s in spans] for c in range(cfg.k)]


def _width(points: DataFrame) -> int:
    row = points.select(F.size("x").alias("n")).first()
    if row is None:
        raise ValueError("there are no samples")
    return row.n


# --- full passes --------------------------------------------------------------------------------------------


def bulk_sums(points: DataFrame, w: list[list[float]], reduce: str = "flat", fan_in: int = 16) -> DataFrame:
    """The sums of ``partial_sums`` by the numpy kernel: each task adds up its Arrow batches and gives k rows."""
    state, names = np.asarray(w, dtype=np.float64), ["block", "sums", "n", "loss", "leaf"]

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        sums, n, loss = np.zeros_like(state), np.zeros(len(state), np.int64), np.zeros(len(state))
        for batch in batches:
            if not batch.num_rows:
                continue
            x = batch.column(0).flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1)
            near, d2 = kernel.nearest(x, state)
            n += np.bincount(near, minlength=len(state))
            loss += np.bincount(near, weights=0.5 * d2, minlength=len(state))
            for j in range(x.shape[1]):
                sums[:, j] += np.bincount(near, weights=x[:, j], minlength=len(state))
        have = np.flatnonzero(n)
        leaf = TaskContext.get().partitionId() % fan_in
        yield pa.RecordBatch.from_arrays([pa.array(have, pa.int32()), pa.array(sums[have].tolist(), pa.list_(pa.float64())), pa.array(n[have]), pa.array(loss[have]), pa.array([leaf] * len(have), pa.int32())], names)

    rows = points.select("x").mapInArrow(run, "block int, sums array<double>, n long, loss double, leaf int")
    for keys in ((["block", "leaf"], ["block"]) if reduce == "tree" else (["block"],)):
        wide = [F.sum(F.col("sums")[j]).alias(f"s{j}") for j in range(state.shape[1])]
        rows = rows.groupBy(*keys).agg(*wide, F.sum("n").alias("n"), F.sum("loss").alias("loss"))
        rows = rows.select(*keys, F.array(*[f"s{j}" for j in range(state.shape[1])]).alias("sums"), "n", "loss")
    return rows


def partial_sums(points: DataFrame, w: list[list[float]], reduce: str = "flat", fan_in: int = 16) -> DataFrame:
    """``block, n, sums array, loss``: what one pass needs, k rows a task before the shuffle; DataFrame functions only.

    The state is one broadcast row, so that every pass runs the same generated code.
    """
    from pyspark.ml.functions import array_to_vector, vector_to_array
    from pyspark.ml.stat import Summarizer

    spark = points.sparkSession
    state = spark.createDataFrame([(w,)], "w array<array<double>>")
    near = points.crossJoin(F.broadcast(state)).select("x", distances("x", F.col("w")).alias("d2"))
    placed = near.select(array_to_vector("x").alias("v"), (F.array_position("d2", F.array_min("d2")) - 1).cast("int").alias("block"), F.array_min("d2").alias("best"), F.pmod(F.xxhash64("x"), F.lit(fan_in)).alias("leaf"))
    sums = [Summarizer.sum(F.col("v")).alias("s"), F.count("*").alias("n"), F.sum(F.col("best") * 0.5).alias("loss")]
    if reduce == "tree":
        leaves = placed.groupBy("block", "leaf").agg(*sums)
        return leaves.groupBy("block").agg(vector_to_array(Summarizer.sum(F.col("s"))).alias("sums"), F.sum("n").alias("n"), F.sum("loss").alias("loss"))
    return placed.groupBy("block").agg(*sums).select("block", vector_to_array("s").alias("sums"), "n", "loss")


def batch_descent(points: DataFrame, cfg: DescentConfig, w0: list | None = None, reduce: str = "flat", sums=bulk_sums) -> RunResult:
    """Full passes: every step uses the mean gradient of all samples. ``sums``: ``bulk_sums`` or ``partial_sums``."""
    w = np.asarray(w0 or initial_state(points, cfg), dtype=np.float64)
    began, trace, start = time.time(), [], w.tolist()
    for t in range(cfg.steps):
        rows = sums(points, w.tolist(), reduce).collect()  # k rows
        m = sum(r.n for r in rows)
        g = np.zeros_like(w)
        for r in rows:
            g[r.block] = (r.n * w[r.block] - np.asarray(r.sums)) / (r.n if cfg.normalise == "cluster" else m)
        trace.append((t, (t + 1) * m, time.time() - began, sum(r.loss for r in rows) / m, 0, 0, 0))
        w = w - cfg.eps * g
        if _stops(cfg, trace):
            break
    states = points.sparkSession.createDataFrame([(0, w.tolist(), 0, 0, 0)], STATE)
    return RunResult(states, cfg, trace, start)


def _stops(cfg: DescentConfig, trace: list[tuple]) -> bool:
    s, (_, touched, secs, error, *_) = cfg.stop, trace[-1]
    return (s.max_touched is not None and touched >= s.max_touched) or (s.max_seconds is not None and secs >= s.max_seconds) or (s.target_error is not None and error is not None and error <= s.target_error)


# --- the worker's rounds ---------------------------------------------------------------------------------------


class Rounds:
    """All workers' rounds with the states that mail can still reach: the fold engine's walk."""

    def __init__(self, cfg: DescentConfig, w0: np.ndarray, letters: dict):
        self.cfg, self.letters = cfg, letters
        self.state = np.repeat(w0[None], cfg.workers, axis=0)
        self.history = {0: self.state}
        self.received, self.good = (np.zeros(cfg.workers, np.int64) for _ in range(2))

    def run(self, batches: dict, on_round=None) -> np.ndarray:
        """``on_round(t, states)`` ends the walk by a true value."""
        cfg, began = self.cfg, time.monotonic()
        for t in range(cfg.steps):
            now = self.state
            after = now.copy()
            steps = {i: kernel.gradient(x, now[i], cfg.reduce, cfg.normalise, cfg.loss) for i in range(cfg.workers) if (x := batches.get((i, t))) is not None}
            if cfg.comm == "sync":  # own steps first; then all read what peers have just reached
                fresh = np.stack([now[i] - cfg.eps * steps[i] if i in steps else now[i] for i in range(cfg.workers)])
            for i, g in steps.items():
                due = self.letters.get((i, t + (cfg.comm == "sync")), ())
                of = [(fresh[s] if cfg.comm == "sync" else self.history[sent + 1][s], np.isin(np.arange(cfg.k), blocks)) for s, sent, blocks in due]
                after[i], good = _moved(cfg, now[i], g, of)
                self.received[i] += len(of)
                self.good[i] += good
            self.state = self.history[t + 1] = after
            if cfg.consume:  # else a state may be read at any later round
                self.history.pop(t - cfg.max_age, None)
            if on_round and on_round(t, after) or cfg.stop.max_seconds is not None and time.monotonic() - began >= cfg.stop.max_seconds:
                break
        return self.state


def _moved(cfg: DescentConfig, w: np.ndarray, g: np.ndarray, letters: list) -> tuple[np.ndarray, int]:
    modified, good = kernel.step(w, g, letters, cfg.eps, cfg.window, cfg.window_scope, cfg.empty_rule)
    return kernel.apply(w, g, modified, cfg.eps, cfg.blend_gain), good


def _sorted_batches(rows: pa.Table) -> dict:
    worker, rnd, slot = (rows.column(c).to_numpy() for c in ("worker", "round", "slot"))
    x = rows.column("x").combine_chunks()
    x = x.flatten().to_numpy().reshape(len(rows), -1)
    order = np.lexsort((slot, rnd, worker))
    worker, rnd, x = worker[order], rnd[order], x[order]
    cuts = np.flatnonzero((np.diff(worker) != 0) | (np.diff(rnd) != 0)) + 1
    starts = [0, *cuts.tolist()]
    return {(int(worker[a]), int(rnd[a])): x[a:b] for a, b in zip(starts, [*cuts.tolist(), len(x)], strict=True)}


TRACED = "run string, round int, secs double, " + STATE


def folded(drawn: DataFrame, cfg: DescentConfig, w0: list) -> DataFrame:
    """The fold engine: final states of a run over ``worker, round, slot, x``."""
    return traced(drawn, cfg, w0, 0).select("worker", "w", "sent", "received", "good")


def traced(drawn: DataFrame, cfg: DescentConfig, w0: list, every: int = 1) -> DataFrame:
    """The states of a run's last round, or after every ``every`` rounds: ``round`` counts those done, ``secs`` the walk's time."""
    return walked(drawn.withColumn("run", F.lit("run")), {"run": (cfg, w0)}, every).drop("run")


def walked(drawn: DataFrame, runs: dict[str, tuple[DescentConfig, list]], every: int = 0) -> DataFrame:
    """Many runs at once, a task each, over ``run, worker, round, slot, x``: the rows of ``traced`` with their run.

    A repeat over seeds or settings is one job; a run's mail is planned in its task.
    """
    for cfg, _ in runs.values():
        if cfg.workers * cfg.b * cfg.steps > FOLD_MOST:
            raise ValueError(f"the fold engine takes at most {FOLD_MOST} samples; use superstep or mailbox")
    kinds = (pa.string(), pa.int32(), pa.float64(), pa.int32(), pa.list_(pa.list_(pa.float64())), *[pa.int64()] * 3)
    names = ["run", "round", "secs", "worker", "w", "sent", "received", "good"]

    def run(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        name = key[0].as_py()
        cfg, start = runs[name]
        start, n, rows = np.asarray(start, dtype=np.float64), cfg.workers, []
        plain = cfg.comm == "silent" and cfg.b == 1 and cfg.loss == "prototypes" and cfg.blend_gain == "eps" and table.num_rows == n * cfg.steps
        x = _cube(table, n, cfg.steps) if plain else _sorted_batches(table)
        rounds = Rounds(cfg, start, {} if cfg.comm == "silent" else mail.inbox(cfg.with_(steps=cfg.steps + (cfg.comm == "sync"))))
        began, passed = time.monotonic(), 0.0

        def keep(t: int, states: np.ndarray) -> bool:
            nonlocal passed
            now = time.monotonic()
            over = t + 1 == cfg.steps or cfg.stop.max_seconds is not None and now - began >= cfg.stop.max_seconds
            if over or every and (t + 1) % every == 0:
                rows.extend((name, t + 1, now - began - passed, i, states[i].tolist(), mail.sent_before(cfg, t + 1), rounds.received[i], rounds.good[i]) for i in range(n))
                passed += time.monotonic() - now  # what keeping costs is not the method's time
            return over

        if plain:
            kernel.alone(x, np.repeat(start[None], n, axis=0), cfg.eps, keep)
        else:
            rounds.run(x, keep)
        return pa.table([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=names)

    return drawn.select("run", "worker", "round", "slot", "x").groupBy("run").applyInArrow(run, TRACED)


def _cube(rows: pa.Table, n: int, steps: int) -> np.ndarray:
    """Single samples as steps x workers x dims."""
    worker, rnd = (rows.column(c).to_numpy() for c in ("worker", "round"))
    x = rows.column("x").combine_chunks().flatten().to_numpy().reshape(len(rows), -1)
    out = np.empty((steps, n, x.shape[1]))
    out[rnd, worker] = x
    return out


HISTORY = "worker int, round int, w array<array<double>>, received long, good long"


def supersteps(drawn: DataFrame, cfg: DescentConfig, w0: list, evaluate: DataFrame | None = None, resume: tuple[DataFrame, int] | None = None, keep_all: bool = False) -> tuple[DataFrame, list[tuple]]:
    """The superstep engine: a job a stretch. ``resume``: history rows ``worker, round, w`` and the round to begin with.

    Messages reach peers at stretch borders; with ``stretch=1`` the run equals the fold engine's, bit for bit. A job reads the
    samples of its stretch and the tables of states that mail can still reach, however many rounds have passed.
    The history has these last states, or with ``keep_all`` those of every round.
    """
    spark = drawn.sparkSession
    sync = cfg.comm == "sync"
    if not cfg.consume:
        raise ValueError("states that stay in buffers have no bounded age: use the fold engine")
    if sync and cfg.stretch > 1:
        raise ValueError("synchronous exchange needs a stretch of 1")
    placed = settled(drawn.withColumn("leg", F.floor(F.col("round") / cfg.stretch).cast("int")).repartitionById(cfg.workers, "worker"), "drawn", "leg")
    ahead = cfg.with_(steps=cfg.steps + sync)
    border = (F.floor(F.col("sent_round") / cfg.stretch) + 1) * cfg.stretch  # what is sent within a stretch is read after it
    late = draws.inbox(spark, ahead).withColumn("round", F.greatest("round", border).cast("int") - int(sync)).where(F.col("round") < cfg.steps)
    legs = late.groupBy("recipient", "round", "buffer", "sender", "sent_round").agg(F.sort_array(F.collect_list("block")).alias("blocks"))
    post = None if cfg.comm == "silent" else settled(legs.withColumn("leg", F.floor(F.col("round") / cfg.stretch).cast("int")), "mail", "leg")
    begin = 0 if resume is None else resume[1]
    tables = [(begin, spark.createDataFrame([(i, 0, w0, 0, 0) for i in range(cfg.workers)], HISTORY) if resume is None else resume[0].select("worker", "round", "w", "received", "good"))]
    trace, began, past = [], time.time(), []

    def letters_of(rows: list[dict]) -> dict:
        found: dict = {}
        for r in sorted((r for r in rows if r["sender"] is not None), key=lambda r: (r["round"], r["buffer"], r["sent_round"], r["sender"])):
            found.setdefault(r["round"], []).append((np.asarray(r["w"]), np.isin(np.arange(cfg.k), r["blocks"])))
        return found

    def work(key, samples: pa.Table, inputs: pa.Table) -> pa.Table:
        worker, rows = key[0].as_py(), inputs.to_pylist()
        own = next(r for r in rows if r["sender"] is None)
        w, received, good = np.asarray(own["w"]), own["received"], own["good"]
        letters, batches = letters_of(rows), _sorted_batches(samples) if samples.num_rows else {}
        out = []
        for t in range(own["round"], own["round"] + min(cfg.stretch, cfg.steps - own["round"])):
            x = batches.get((worker, t))
            if x is not None:
                g = kernel.gradient(x, w, cfg.reduce, cfg.normalise, cfg.loss)
                w, n = _moved(cfg, w, g, letters.get(t, []))
                received, good = received + len(letters.get(t, [])), good + n
            out.append((worker, t + 1, w.tolist(), received, good))
        return pa.table([pa.array(c, type=k) for c, k in zip(zip(*out, strict=True), _HISTORY_KINDS, strict=True)], names=["worker", "round", "w", "received", "good"])

    def alone(key, samples: pa.Table, inputs: pa.Table) -> pa.Table:
        """The first half of a synchronous round: the own step, and where it leads."""
        (own,) = inputs.to_pylist()
        w, (x,) = np.asarray(own["w"]), _sorted_batches(samples).values() if samples.num_rows else (None,)
        g = None if x is None else kernel.gradient(x, w, cfg.reduce, cfg.normalise, cfg.loss)
        fresh = w if g is None else w - cfg.eps * g
        kinds = (pa.int32(), *[pa.list_(pa.list_(pa.float64()))] * 3, pa.int64(), pa.int64())
        return pa.table([pa.array([v], type=k) for v, k in zip((own["worker"], own["w"], None if g is None else g.tolist(), fresh.tolist(), own["received"], own["good"]), kinds, strict=True)], names=["worker", "w", "g", "fresh", "received", "good"])

    def meet(key, mine: pa.Table, inputs: pa.Table) -> pa.Table:
        """The second half: fresh states of peers are read."""
        (own,), rows = mine.to_pylist(), inputs.to_pylist()
        w, received, good = np.asarray(own["w"]), own["received"], own["good"]
        if own["g"] is not None:
            due = next(iter(letters_of(rows).values()), [])
            w, n = _moved(cfg, w, np.asarray(own["g"]), due)
            received, good = received + len(due), good + n
        return pa.table([pa.array([v], type=k) for v, k in zip((own["worker"], 0, w.tolist(), received, good), _HISTORY_KINDS, strict=True)], names=["worker", "round", "w", "received", "good"])

    nothing = [F.lit(None).cast(t).alias(c) for c, t in (("sender", "int"), ("sent_round", "int"), ("buffer", "int"), ("blocks", "array<int>"))]
    written = [F.col("recipient").alias("worker"), "round", "w", F.lit(0).cast("long").alias("received"), F.lit(0).cast("long").alias("good"), "sender", "sent_round", "buffer", "blocks"]
    for t in range(begin, cfg.steps, cfg.stretch):
        end = min(t + cfg.stretch, cfg.steps)
        leg = t // cfg.stretch
        now = tables[-1][1].where(F.col("round") == t)
        slice_ = placed.where((F.col("leg") == leg) & (F.col("round") >= t)).drop("leg")
        due = None if post is None else post.where((F.col("leg") == leg) & (F.col("round") >= t)).drop("leg")
        if sync:
            halves = settled(slice_.groupBy("worker").cogroup(now.groupBy("worker")).applyInArrow(alone, "worker int, w array<array<double>>, g array<array<double>>, fresh array<array<double>>, received long, good long"), "halves")
            letters = due.join(halves.select(F.col("worker").alias("sender"), F.col("fresh").alias("w")), "sender").select(*written)
            made = settled(halves.groupBy("worker").cogroup(letters.groupBy("worker")).applyInArrow(meet, HISTORY).withColumn("round", F.lit(t + 1).cast("int")), "states")
        else:
            inputs = now.select("worker", "round", "w", "received", "good", *nothing)
            if due is not None:
                states = reduce(DataFrame.unionByName, [h for _, h in tables]).select(F.col("worker").alias("sender"), (F.col("round") - 1).alias("sent_round"), "w")
                inputs = inputs.unionByName(due.where(F.col("sent_round") < t).join(states, ["sender", "sent_round"]).select(*written))
            made = settled(slice_.groupBy("worker").cogroup(inputs.groupBy("worker")).applyInArrow(work, HISTORY), "states")
        reach = max(cfg.max_age, cfg.stretch) + 1
        past += [made] * keep_all
        tables = [(last, h) for last, h in tables if cfg.comm != "silent" and last > end - reach] + [(end, made)]
        counts = made.where(F.col("round") == end).agg(F.sum("received"), F.sum("good"), F.min_by("w", "worker")).first()
        error = error_of(evaluate, counts[2], cfg.loss) if evaluate is not None else None
        sent = cfg.workers * mail.sent_before(cfg, end)
        trace.append((end, end * cfg.b * cfg.workers, time.time() - began, error, sent, counts[0], counts[1]))
        if _stops(cfg, trace):
            break
    return reduce(DataFrame.unionByName, past if keep_all and past else [h for _, h in tables]), trace


_HISTORY_KINDS = (pa.int32(), pa.int32(), pa.list_(pa.list_(pa.float64())), pa.int64(), pa.int64())


def latest(history: DataFrame, spark: SparkSession, cfg: DescentConfig, upto: int | None = None) -> DataFrame:
    """STATE rows of the last round in the history; ``upto``: the rounds done, all of the run's if not given."""
    sent = F.lit(mail.sent_before(cfg, cfg.steps if upto is None else upto)).cast("long").alias("sent")
    last = history.groupBy("worker").agg(F.max_by(F.struct("w", "received", "good"), "round").alias("s"))
    return last.select("worker", "s.w", sent, "s.received", "s.good")


def error_of(points: DataFrame, w: list, loss: str = "prototypes") -> float:
    """Mean loss of a state over all points; of prototypes the mean quantisation error."""
    return errors_of(points, [np.asarray(w, dtype=np.float64)], loss)[0]


def errors_of(points: DataFrame, states: list[np.ndarray], loss: str = "prototypes") -> list[float]:
    """Mean losses of several states over all points, in one pass: a row for each task and state."""
    if not states:
        return []
    sent = points.sparkSession.sparkContext.broadcast(states)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums, n = np.zeros(len(sent.value)), 0
        for batch in batches:
            if batch.num_rows:
                x = batch.column(0).flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1)
                sums += [kernel.losses(x, w, loss).sum() for w in sent.value]
                n += batch.num_rows
        yield pa.RecordBatch.from_arrays([pa.array(range(len(sums)), pa.int32()), pa.array(sums), pa.array([n] * len(sums), pa.int64())], ["state", "loss", "n"])

    rows = points.select("x").mapInArrow(run, "state int, loss double, n long").groupBy("state").agg((F.sum("loss") / F.sum("n")).alias("error")).collect()
    return [r.error for r in sorted(rows, key=lambda r: r.state)]


# --- methods -----------------------------------------------------------------------------------------------------


def gossip_sgd(points: DataFrame, cfg: DescentConfig, w0: list | DataFrame | None = None, engine: str = "auto", evaluate: DataFrame | None = None) -> RunResult:
    """Windowed gossip descent; ``comm="silent"`` leaves messages out, ``"sync"`` waits for fresh states.

    ``w0``: blocks of values, or a stored state ``block, dim, value`` (a warm start).
    """
    m = points.count()
    cfg = cfg.validate(m).within()
    start = as_array(w0).tolist() if isinstance(w0, DataFrame) else w0 or initial_state(points, cfg)
    drawn = draws.minibatches(points, cfg, m)
    if engine == "auto":
        engine = "fold" if cfg.workers * cfg.b * cfg.steps <= FOLD_MOST and evaluate is None else "superstep"
    if cfg.stop.target_error is not None and (engine != "superstep" or evaluate is None):
        raise ValueError("an error level needs the superstep engine and points to evaluate on")
    if engine == "fold":
        return RunResult(folded(drawn, cfg, start), cfg, w0=start)
    if engine == "superstep":
        history, trace = supersteps(drawn, cfg, start, evaluate)
        return RunResult(latest(history, points.sparkSession, cfg, trace[-1][0]), cfg, trace, start)
    if engine == "mailbox":
        if not cfg.consume:
            raise ValueError("the mailbox engine reads each state once")
        if cfg.comm == "sync":
            raise ValueError("the mailbox engine never waits: synchronous exchange runs on fold and superstep")
        from gossamer.operators.mailbox import mailbox_run

        return RunResult(mailbox_run(drawn, cfg, start), cfg, w0=start)
    raise ValueError(f"no engine {engine!r}")


def oneshot_sgd(points: DataFrame, cfg: DescentConfig, w0: list | None = None, engine: str = "auto", final: str = "average") -> RunResult:
    """Workers run alone on single samples; one average at the end. ``arrow``: a worker a task, batches streamed.

    ``final="first"`` is the variant that returns one worker. ``auto`` streams what the fold engine would not take.
    """
    cfg = cfg.with_(comm="silent", b=1, final=final).within()
    if engine == "auto":
        m, per = points.count(), cfg.workers * cfg.steps
        engine = "fold" if per <= FOLD_MOST or per > m // cfg.workers * cfg.workers or cfg.loss != "prototypes" else "arrow"
    if engine != "arrow":
        return gossip_sgd(points, cfg, w0, engine)
    m = points.count()
    cfg.validate(m)
    if cfg.workers * cfg.steps > m // cfg.workers * cfg.workers:
        raise ValueError("streamed workers walk their samples once")
    start = w0 or initial_state(points, cfg)
    parted = draws.assign_workers(points, cfg.workers, cfg.seed, m, budget=cfg.workers * cfg.steps).repartitionById(cfg.workers, "worker").sortWithinPartitions("worker", "pos")

    return RunResult(streamed(parted.select("worker", "x"), cfg, start), cfg, w0=start)


def streamed(parted: DataFrame, cfg: DescentConfig, start: list) -> DataFrame:
    """Final states of workers that step alone over ``worker, x``, each worker's samples in order in one partition."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        states: dict[int, np.ndarray] = {}
        for batch in batches:
            if not batch.num_rows:
                continue
            x, who = batch.column(1).flatten().to_numpy().reshape(batch.num_rows, 1, -1), batch.column(0).to_numpy()
            cuts = [0, *(np.flatnonzero(np.diff(who)) + 1).tolist(), len(who)]
            for a, b in zip(cuts, cuts[1:], strict=False):
                worker = int(who[a])
                w = states.get(worker, np.asarray(start, dtype=np.float64))
                states[worker] = kernel.alone(x[a:b], w[None], cfg.eps)[0]
        if states:
            n = len(states)
            yield pa.RecordBatch.from_arrays([pa.array(list(states), pa.int32()), pa.array([s.tolist() for s in states.values()], pa.list_(pa.list_(pa.float64()))), *[pa.array([0] * n, pa.int64())] * 3], ["worker", "w", "sent", "received", "good"])

    return parted.mapInArrow(run, STATE)


def minibatch_sgd(points: DataFrame, cfg: DescentConfig, w0: list | None = None, engine: str = "auto") -> RunResult:
    """One worker, ``b`` samples a step."""
    return gossip_sgd(points, cfg.with_(comm="silent", workers=1), w0, engine)


def online_sgd(points: DataFrame, cfg: DescentConfig, w0: list | None = None, engine: str = "auto") -> RunResult:
    """One worker, one sample a step, drawn with replacement."""
    return gossip_sgd(points, cfg.with_(comm="silent", workers=1, b=1, draw="replace"), w0, engine)


def assigned(points: DataFrame, w: list) -> DataFrame:
    """``sample_id, cluster``"""
    state = points.sparkSession.createDataFrame([(w,)], "w array<array<double>>")
    return points.crossJoin(F.broadcast(state)).select("sample_id", assign("x", F.col("w")).alias("cluster"))
