"""All registered queries of the descent engine, with SQL wherever SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gossamer.config import DescentConfig, StopRule
from gossamer.functions import arrays as A
from gossamer.functions import kernel
from gossamer.operators import codebook, descent, draws, linear, metrics
from gossamer.plans import experiments, oracle, reports, surround
from gossamer.sources import points as S
from gossamer.sources.shared import settled
from gossamer.streaming import stream

CFG = DescentConfig()
VARIANTS = {
    "gossip_full": ({}, "first"), "gossip_silent": ({"comm": "silent"}, "first"), "gossip_nowindow": ({"window": False}, "first"), "gossip_two_buffers": ({"buffers": 2, "fanout": 2}, "first"), "gossip_partial": ({"block_frac": 0.5}, "first"),
    "gossip_fanout2": ({"fanout": 2}, "first"), "gossip_delay2": ({"max_age": 2}, "first"), "gossip_torn": ({"race": "torn", "fanout": 3, "block_frac": 0.5}, "first"), "gossip_lossless": ({"race": "none", "fanout": 2}, "first"), "gossip_every": ({"comm_every": 3}, "first"), "gossip_average": ({}, "average"),
    "gossip_persample": ({"b": 1, "steps": 24}, "first"), "gossip_sum": ({"reduce": "sum", "eps": 0.05}, "first"), "gossip_replace": ({"draw": "replace"}, "first"),
    "gossip_sync": ({"comm": "sync"}, "first"), "gossip_other_node": ({"threads": 2, "scope": "other_node"}, "first"), "gossip_geometric": ({"delay": "geometric", "max_age": 3}, "first"), "gossip_zero_norm": ({"empty_rule": "zero_norm", "block_frac": 0.4}, "first"),
    "gossip_whole_states": ({"window_scope": "state", "fanout": 3, "race": "torn", "block_frac": 1.0}, "first"), "gossip_kept_buffers": ({"consume": False, "buffers": 2, "comm_every": 2}, "first"), "gossip_kept_torn": ({"consume": False, "race": "torn", "fanout": 2, "block_frac": 0.5}, "first"), "gossip_hashed": ({"partition": "hash"}, "first"), "gossip_global_draws": ({"draw": "replace", "draw_from": "global"}, "first"), "gossip_unit_gain": ({"blend_gain": "unit"}, "first"), "gossip_cluster_mean": ({"normalise": "cluster"}, "first"), "gossip_init_sample": ({"init": "sample"}, "first"), "gossip_stopped": ({"stop": StopRule(max_touched=100)}, "first"), "lockfree_torn": ({"race": "torn", "window": False}, "first"),
    "oneshot_first": ({"comm": "silent", "b": 1, "steps": 40, "eps": 0.1}, "first"), "oneshot_average": ({"comm": "silent", "b": 1, "steps": 40, "eps": 0.1}, "average"), "minibatch_sgd": ({"comm": "silent", "workers": 1, "b": 16}, "first"), "online_sgd": ({"comm": "silent", "workers": 1, "b": 1, "steps": 60, "draw": "replace", "eps": 0.1}, "first"),
}
Query = Callable[[SparkSession, str], DataFrame]


def _finished(states: DataFrame, final: str) -> DataFrame:
    return descent.first(states) if final == "first" else descent.average(states).withColumn("value", F.round("value", 9))


def _run(name: str) -> Query:
    changes, final = VARIANTS[name]

    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        return _finished(descent.gossip_sgd(S.line4(spark, sf_dir), CFG.with_(**changes, final=final)).states, final)

    return query


def _scalars(points: DataFrame) -> DataFrame:
    return points.select("sample_id", F.posexplode("x").alias("dim", "value"))


def _w(k: int, points: DataFrame) -> list:
    return descent.initial_state(points, CFG.with_(k=k))


def _with_state(points: DataFrame, k: int = 3) -> DataFrame:
    state = points.sparkSession.createDataFrame([(_w(k, points),)], "w array<array<double>>")
    return points.crossJoin(F.broadcast(state))


def kmeans_assign(spark, sf_dir):
    return _with_state(S.emb64(spark, sf_dir)).select("sample_id", A.assign("x", F.col("w")).alias("cluster"))


def kmeans_error(spark, sf_dir):
    return _with_state(S.line4(spark, sf_dir)).select(F.array_min(A.distances("x", F.col("w"))).alias("d2")).agg(F.round(F.sum(F.col("d2") * 0.5), 6).alias("total"), F.round(F.avg(F.col("d2") * 0.5), 9).alias("mean"))


def kmeans_grad_mean(spark, sf_dir):
    points = S.line4(spark, sf_dir)
    w = _w(3, points)
    rows = descent.partial_sums(points, w)
    m = points.count()
    state = spark.createDataFrame([(i, v) for i, v in enumerate(w)], "block int, c array<double>")
    each = state.join(rows, "block", "left").select("block", F.posexplode("c").alias("dim", "c"), "n", "sums")
    return each.select("block", "dim", ((F.coalesce("n", F.lit(0)) * F.col("c") - F.coalesce(F.col("sums")[F.col("dim")], F.lit(0.0))) / m).alias("value")).withColumn("value", rounded("value"))


def kmeans_grad_one(spark, sf_dir):
    near = _with_state(S.line4(spark, sf_dir)).select("sample_id", "x", "w", A.distances("x", F.col("w")).alias("d2")).select("sample_id", "x", A.nearest("d2").alias("block"), "w")
    g = F.zip_with(F.col("w")[F.col("block")], "x", lambda a, b: a - b)
    return near.select("sample_id", "block", F.posexplode(g).alias("dim", "value"))


def rounded(name: str):
    """Nine places, moved off decimal ties, which sums of decimals meet and engines round apart."""
    return F.round(F.col(name) + 1.7e-11, 9)


def _batch(steps: int, reduce: str = "flat", sums=descent.bulk_sums) -> Query:
    def query(spark, sf_dir):
        r = descent.batch_descent(S.line4(spark, sf_dir), CFG.with_(eps=1.0, steps=steps), reduce=reduce, sums=sums)
        return descent.first(r.states).withColumn("value", rounded("value"))

    return query


def partition_report(spark, sf_dir):
    parted = draws.assign_workers(S.line4(spark, sf_dir), 7, CFG.seed)
    return parted.groupBy("worker").agg(F.count("*").alias("n"), F.max("pos").alias("last_pos"))


def window_accept_cases(spark, sf_dir):
    rows = spark.createDataFrame([(i, [[2.0]], [[1.0]], None if e is None else [[e]]) for i, e in enumerate((1.0, 1.5, 0.0, 3.0, 2.0, 1.75, None))], "id int, w array<array<double>>, g array<array<double>>, e array<array<double>>")
    return rows.select("id", A.window_accept("w", "g", 0.5, "e").alias("accepted"))


def blend_cases(spark, sf_dir):
    """Orders as cases: the first item's quantity is the own state, a sample in the middle gives the step, the other items' are received."""
    place = F.struct("l_linenumber", "l_partkey", "l_suppkey", (F.col("l_quantity") / 50.0).alias("q"))
    orders = S.table(spark, sf_dir, "lineitem").where("l_quantity is not null").groupBy("l_orderkey").agg(F.transform(F.array_sort(F.collect_list(place)), lambda i: i["q"]).alias("qs"))
    own, block = F.col("qs")[0], lambda v: F.array(F.array(v))
    rows = orders.select("l_orderkey", block(own).alias("w"), block(own - 0.5).alias("g"), F.transform(F.slice("qs", 2, F.greatest(F.size("qs") - 1, F.lit(0))), block).alias("es"))
    ok = F.filter("es", lambda e: A.window_accept("w", "g", 0.5, e))
    step = lambda of: A.moved("w", of, 0.5)[0][0]
    return rows.withColumn("ok", ok).select("l_orderkey", F.size("ok").alias("accepted"), step(A.blended("w", "g", "ok")).alias("windowed"), step(A.blended("w", "g", "es")).alias("open"))


#: settings of queries on mail between workers whose users act in the events
MAIL = {"recipients": CFG.with_(workers=9, fanout=3, max_age=3, buffers=2), "blocks": CFG.with_(k=6, block_frac=0.4), "torn": CFG.with_(fanout=3, race="torn", block_frac=0.5), "settled": CFG.with_(fanout=2, block_frac=0.5, max_age=2, buffers=2)}


def event_mail(spark: SparkSession, sf_dir: str, cfg: DescentConfig) -> DataFrame:
    """A round an hour: a worker writes in the hours in which its users act."""
    return draws.addressed(S.acting(spark, sf_dir, cfg.workers), cfg)


def _settled(race: str) -> Query:
    cfg = MAIL["settled"]
    return lambda spark, sf_dir: draws.settle(draws.blocks(event_mail(spark, sf_dir, cfg), cfg), race).select("recipient", "round", "buffer", "block", "sender", "sent_round")


def inbox_torn(spark, sf_dir):
    """The settled mail up to the last hour in which a worker writes."""
    cfg = MAIL["torn"]
    last = S.acting(spark, sf_dir, cfg.workers).agg(F.max("sent_round")).first()[0]
    return draws.inbox(spark, cfg.with_(steps=(-1 if last is None else last) + 1), event_mail(spark, sf_dir, cfg))


def message_rates(spark, sf_dir):
    """Messages sent, received and counted of each worker, and for each mini-batch."""
    rate = lambda c: F.round(F.col(c) / CFG.steps, 6).alias(f"{c}_rate")
    return descent.gossip_sgd(S.line4(spark, sf_dir), CFG).states.select("worker", "sent", "received", "good", *[rate(c) for c in ("sent", "received", "good")])


def race_counts(spark, sf_dir):
    cfg = MAIL["torn"]
    sent = event_mail(spark, sf_dir, cfg)
    return draws.race_counts(sent, draws.settle(draws.blocks(sent, cfg), "torn"))


def worker_spread(spark, sf_dir):
    return metrics.worker_spread(descent.gossip_sgd(S.line4(spark, sf_dir), CFG).states).withColumn("spread", F.round("spread", 9))


def center_error(spark, sf_dir):
    points = S.line4(spark, sf_dir)
    state = spark.createDataFrame([(i, v) for i, v in enumerate(_w(5, points))], "block int, w array<double>")
    truth = spark.createDataFrame([(0, [0.2, 0.2, 0.2, 0.2]), (1, [0.8, 0.5, 0.5, 0.5]), (2, [0.5, 0.9, 0.1, 0.7])], "center int, mu array<double>")
    return metrics.center_error_frame(truth, state)


def gossip_resume(spark, sf_dir):
    """Stopped half-way and continued from the written states: the same as the straight run."""
    points = S.line4(spark, sf_dir)
    w0, drawn = descent.initial_state(points, CFG), draws.minibatches(points, CFG)
    half, _ = descent.supersteps(drawn, CFG.with_(steps=4), w0)
    full, _ = descent.supersteps(drawn, CFG, w0, resume=(half, 4))
    return descent.first(descent.latest(full, spark, CFG))


def gossip_superstep(spark, sf_dir):
    return descent.first(descent.gossip_sgd(S.line4(spark, sf_dir), CFG, engine="superstep").states)


def gossip_limit_equals_oneshot(spark, sf_dir):
    """Messages that never leave, single samples and a final average, beside one-shot: the same values twice."""
    points, cfg = S.line4(spark, sf_dir), CFG.with_(b=1, steps=20, final="average")
    runs = {"gossip": descent.gossip_sgd(points, cfg.with_(comm_every=21)), "oneshot": descent.oneshot_sgd(points, cfg, engine="arrow")}
    both = [descent.average(r.states).select(F.lit(name).alias("method"), "block", "dim", F.round("value", 9).alias("value")) for name, r in runs.items()]
    return both[0].unionByName(both[1])


def label_changes(spark, sf_dir):
    points = S.line4(spark, sf_dir)
    w0 = _w(3, points)
    r = descent.batch_descent(points, CFG.with_(eps=1.0, steps=1), w0)
    w1 = descent.as_array(descent.first(r.states)).tolist()
    return descent.assigned(points, w0).exceptAll(descent.assigned(points, w1)).groupBy("cluster").agg(F.count("*").alias("changed"))


def topk_nearest(spark, sf_dir):
    near = _with_state(S.emb64(spark, sf_dir)).select("sample_id", F.posexplode(A.distances("x", F.col("w"))).alias("block", "d2"))
    return near.withColumn("place", F.row_number().over(Window.partitionBy("block").orderBy("d2", "sample_id"))).where("place <= 10").select("block", "place", "sample_id", "d2")


def outliers(spark, sf_dir):
    far = _with_state(S.emb64(spark, sf_dir)).select("sample_id", F.array_min(A.distances("x", F.col("w"))).alias("d2"))
    return far.orderBy(F.desc("d2"), "sample_id").limit(20)


def antijoin_untouched(spark, sf_dir):
    points = S.line4(spark, sf_dir)
    drawn = draws.minibatches(points, CFG).select("sample_id")
    return points.join(drawn, "sample_id", "left_anti").agg(F.count("*").alias("untouched"))


def asof_mail(spark, sf_dir):
    """For each hour in which a worker acts the newest message sent to it no later; workers write in every second hour."""
    acting = S.acting(spark, sf_dir, CFG.workers)
    sent = draws.addressed(acting.where("(sent_round + 1) % 2 = 0"), CFG)
    return draws.newest(acting.select(F.col("sender").alias("worker"), F.col("sent_round").alias("t")), sent)


def codebook_histogram(spark, sf_dir):
    points = S.emb64(spark, sf_dir)
    groups = S.table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("string").alias("sample_id"), F.col("label").alias("object"))
    return codebook.histogram(points, _w(3, points), groups)


CODEBOOK = CFG.with_(k=20, b=16, steps=6)


def codebook_documents(spark, sf_dir):
    """A codebook learnt on hashed documents, as histograms of languages."""
    points = settled(S.doc128(spark, sf_dir), "documents")
    w = descent.as_array(descent.gossip_sgd(points, CODEBOOK).state()).tolist()
    groups = S.table(spark, sf_dir, "documents").select(F.col("doc_id").cast("string").alias("sample_id"), F.col("lang").alias("object"))
    return codebook.histogram(points, w, groups)


def state_round_trip(spark, sf_dir):
    states = descent.gossip_sgd(S.line4(spark, sf_dir), CFG).states
    return descent.first(descent.nested_form(descent.long_form(states)).select("worker", "w"))


def events_json(spark, sf_dir):
    e = S.table(spark, sf_dir, "events").select("event_type", F.from_json("props", "k int")["k"].alias("k"))
    return e.groupBy("event_type", (F.floor(F.col("k") / 10)).cast("int").alias("bin")).agg(F.count("*").alias("n"))


def quantiles(spark, sf_dir):
    t = S.table(spark, sf_dir, "lineitem")
    return t.groupBy("l_returnflag").agg(F.round(F.percentile("l_extendedprice", 0.5), 4).alias("median"), F.round(F.percentile("l_extendedprice", 0.9), 4).alias("p90"))


def sketches(spark, sf_dir):
    """Approximate distinct counts and quantiles (rows only: sketches differ between engines)."""
    t = S.table(spark, sf_dir, "lineitem")
    return t.groupBy("l_returnflag").agg(F.approx_count_distinct("l_orderkey").alias("orders"), F.percentile_approx("l_extendedprice", 0.5).alias("median"))


def udf_surface(spark, sf_dir):
    """Squared distances by expression, Arrow function, SQL function and table function, and their largest in a group."""
    @F.pandas_udf("double")
    def far(x: pd.Series, c: pd.Series) -> pd.Series:
        if not len(x):
            return pd.Series([], dtype="float64")
        d = np.stack(x.to_numpy()) - np.stack(c.to_numpy())
        return pd.Series(kernel.in_order(d * d))

    @F.pandas_udf("double")
    def furthest(d: pd.Series) -> float:
        return float(d.max())

    @F.udtf(returnType="d double")
    class Far:
        def eval(self, x: list):
            total = 0.0
            for v in x:
                total += (v - 0.5) * (v - 0.5)
            yield (total,)

    A.register_functions(spark)
    spark.udtf.register("far_rows", Far)
    c = F.array(*[F.lit(0.5)] * 4)
    rows = S.line4(spark, sf_dir).withColumn("corner", F.floor(F.col("x")[0] * 4).cast("int"))
    ways = rows.select("corner", "x", A.sqdist("x", c).alias("expression"), far("x", c).alias("arrow"), F.expr("sqdist(x, array(0.5D, 0.5D, 0.5D, 0.5D))").alias("sql"))
    named = spark.sql("SELECT r.corner, r.expression, r.arrow, r.sql, t.d AS rows FROM {ways} r, LATERAL far_rows(r.x) t", ways=ways)
    return named.groupBy("corner").agg(*[furthest(w).alias(w) for w in ("expression", "arrow", "sql", "rows")])


def sinks_round_trip(spark, sf_dir):
    """A state table through Parquet, ORC, JSON and CSV: what is read back of each."""
    from gossamer.sources.shared import shared_dir

    rows = settled(descent.long_form(descent.gossip_sgd(S.line4(spark, sf_dir), CFG).states).coalesce(1), "states")
    folder, every = f"{shared_dir(spark)}/sinks", None
    for kind in ("parquet", "orc", "json", "csv"):
        rows.write.mode("overwrite").partitionBy("worker").format(kind).save(f"{folder}-{kind}")
        back = spark.read.schema("block int, dim int, value double, worker int").format(kind).load(f"{folder}-{kind}").select(rows.columns)
        one = back.withColumn("kind", F.lit(kind))
        every = one if every is None else every.unionByName(one)
    return every


def mailbox_async(spark, sf_dir):
    """Timing decides what arrives: rows only."""
    return descent.gossip_sgd(S.line4(spark, sf_dir), CFG.with_(workers=2, steps=20), engine="mailbox").states.select("worker", "sent", "received", "good")


def _event_files(spark: SparkSession, sf_dir: str, part) -> str:
    """A folder for one run, with the events as four files under ``in``, oldest first."""
    import time
    import uuid

    from gossamer.sources.shared import shared_dir

    folder = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    events = S.table(spark, sf_dir, "events")
    for k in range(4):  # a stream reads files by their age
        events.where(part == k).coalesce(1).write.parquet(f"{folder}/in/part={k}")
        time.sleep(0.02)
    return folder


def stream_foreach(spark, sf_dir):
    """Events replayed as four files; the state after each micro-batch (rows only)."""
    each = -(-S.table(spark, sf_dir, "events").count() // 4)
    folder = _event_files(spark, sf_dir, F.floor(F.col("event_id") / each))
    cfg = CFG.with_(workers=2)
    w0 = descent.initial_state(S.evt3(spark, sf_dir), cfg)
    stream.descend_stream(stream.replay(spark, f"{folder}/in/*"), cfg, w0, f"{folder}/model", f"{folder}/log").awaitTermination()
    return spark.read.parquet(f"{folder}/model/3").select("block", F.posexplode("v").alias("dim", "value"))


def _streamed_windows(kind: str) -> Query:
    """The windows of ``_windows`` by a stream over four files: the same rows. Files are in shuffled order, but in order of
    time for sessions, from which the engine leaves out late events whatever the output mode."""

    def query(spark, sf_dir):
        each = -(-S.table(spark, sf_dir, "events").count() // 4)
        folder = _event_files(spark, sf_dir, F.floor(F.col("event_id") / each) if kind == "session" else F.pmod("event_id", F.lit(4)))
        stream.played(stream.windows(stream.raw(spark, f"{folder}/in/*"), kind), "complete", f"{folder}/out", f"{folder}/log")
        return spark.read.parquet(f"{folder}/out")

    return query


#: files of the late replay: the third quarter of events comes first, the first one last
LATE = (3, 1, 0, 2)


def late_events(spark, sf_dir):
    """Events by hour when quarters arrive in a wrong order: what came in time, and how many came too late."""
    events = S.table(spark, sf_dir, "events")
    each = -(-events.count() // 4)
    place = F.element_at(F.array(*map(F.lit, LATE)), (F.floor(F.col("event_id") / each) + 1).cast("int"))
    folder = _event_files(spark, sf_dir, place)
    stream.played(stream.hourly(stream.raw(spark, f"{folder}/in/*")), "update", f"{folder}/out", f"{folder}/log")
    kept = spark.read.parquet(f"{folder}/out").groupBy("start_us").agg(F.max("n").alias("n"))
    hour = 3600 * 10**6
    came = events.groupBy((F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / hour) * hour).alias("start_us")).agg(F.count("*").alias("came"))
    return came.join(kept, "start_us", "left").select("start_us", F.coalesce("n", F.lit(0)).cast("long").alias("n"), (F.col("came") - F.coalesce("n", F.lit(0))).cast("long").alias("late"))


#: the methods on losses with a target: changes to the configuration, and what is returned
LINEAR = {"gossip": ({}, "first"), "oneshot": ({"comm": "silent", "b": 1, "steps": 40}, "average"), "online": ({"comm": "silent", "workers": 1, "b": 1, "steps": 60, "draw": "replace"}, "first"), "minibatch": ({"comm": "silent", "workers": 1, "b": 16}, "first")}


def _linear_cfg(kind: str, method: str) -> DescentConfig:
    return CFG.with_(loss=kind, k=1, eps=0.1, **LINEAR[method][0])


def with_target(spark: SparkSession, sf_dir: str, kind: str) -> DataFrame:
    """Samples that end with a target: the price by quantity, discount, tax and one, or whether it is above the middle."""
    x = F.col("x")
    y = x[1] if kind == "squares" else (x[1] > 0.5).cast("double")
    return S.line4(spark, sf_dir).select("sample_id", F.array(x[0], x[2], x[3], F.lit(1.0), y).alias("x"))


def _target_sql(kind: str) -> str:
    y = "x[2]" if kind == "squares" else "CASE WHEN x[2] > 0.5 THEN 1.0::double ELSE 0.0::double END"
    return f"SELECT sample_id, [x[1], x[3], x[4], 1.0::double, {y}] AS x FROM ({L4}) p"


def _linear_run(kind: str, method: str) -> Query:
    def query(spark, sf_dir):
        states = descent.gossip_sgd(with_target(spark, sf_dir, kind), _linear_cfg(kind, method)).states
        final = descent.first(states) if LINEAR[method][1] == "first" else descent.average(states)
        return final.withColumn("value", F.round("value", 9))

    return query


def _linear(kind: str) -> Query:
    def query(spark, sf_dir):
        rows = S.line4(spark, sf_dir).select(F.array(F.col("x")[0], F.col("x")[2], F.col("x")[3], F.lit(1.0)).alias("x"), F.col("x")[1].alias("y"))
        rows = rows if kind == "squares" else rows.withColumn("y", (F.col("y") > 0.5).cast("double"))
        w = linear.linear_batch(rows, kind, 0.5, 3)
        return spark.createDataFrame(list(enumerate(w)), "dim int, value double").withColumn("value", F.round("value", 6))

    return query


def _windows(kind: str) -> Query:
    return lambda spark, sf_dir: stream.windows(S.table(spark, sf_dir, "events"), kind)


TOUCHING = {"oneshot": CFG.with_(b=1), "online": CFG.with_(workers=1, b=1, draw="replace"), "minibatch": CFG.with_(workers=1), "gossip": CFG}


def touched_samples(spark, sf_dir):
    """Samples that each method touches: as the rule says, and as its draws are counted (batch: its passes)."""
    points = S.line4(spark, sf_dir)
    m = points.count()
    counted = {name: draws.minibatches(points, cfg, m).count() for name, cfg in TOUCHING.items()} | {"batch": CFG.steps * m}
    rows = [(name, metrics.touched(name, CFG.steps, m, CFG.workers, CFG.b), n) for name, n in counted.items()]
    return spark.createDataFrame(rows, "method string, touched long, counted long")


def _mix(spark: SparkSession) -> DataFrame:
    return S.mix(spark, 10, 4000, 10, tasks=8)


def library_kmeans(spark, sf_dir):
    """The library's own clustering as an independent line: its mean error is not far above that of ten passes."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    points = S.line4(spark, sf_dir)
    fitted = KMeans(k=3, seed=CFG.seed, maxIter=10, featuresCol="v").fit(points.select(array_to_vector("x").alias("v")))
    own = descent.batch_descent(points, CFG.with_(eps=1.0, steps=10))
    errors = descent.errors_of(points, [np.asarray([list(map(float, c)) for c in fitted.clusterCenters()]), descent.as_array(own.state())])
    return spark.createDataFrame([("library", errors[0]), ("batch", errors[1])], "method string, error double")


def label_changes_sql() -> str:
    near = lambda w: f"SELECT p.sample_id, (list_position(ds, list_min(ds)) - 1)::int AS cluster FROM (SELECT p.sample_id, list_transform(z.w, lambda c: {oracle.d2('p.x', 'c', 4)}) AS ds FROM ({L4}) p, ({w}) z) p"
    after = f"SELECT list(v ORDER BY block) AS w FROM (SELECT block, list(value ORDER BY dim) AS v FROM ({oracle.batch(L4, CFG.with_(eps=1.0, steps=1), 4)}) b GROUP BY block) c"
    return f"SELECT cluster, count(*) AS changed FROM (SELECT * FROM ({near(oracle.initial(L4, CFG))}) a EXCEPT ALL SELECT * FROM ({near(after)}) b) d GROUP BY cluster"


def race_counts_sql() -> str:
    cfg = MAIL["torn"]
    sent, stood = oracle.sends(cfg, oracle.acting(cfg.workers)), oracle.settled(cfg, oracle.acting(cfg.workers))
    return f"SELECT d.round, d.due, d.due - k.kept AS lost, t.torn FROM (SELECT due_round AS round, count(*) AS due FROM ({sent}) s GROUP BY 1) d JOIN (SELECT round, count(DISTINCT (recipient, sender, sent_round, buffer)) AS kept FROM ({stood}) s GROUP BY 1) k USING (round) JOIN (SELECT round, sum((n > 1)::bigint)::bigint AS torn FROM (SELECT round, recipient, buffer, count(DISTINCT (sender, sent_round)) AS n FROM ({stood}) s GROUP BY ALL) u GROUP BY 1) t USING (round)"


def blend_sql() -> str:
    """Orders as cases of the step: own state, gradient, received states."""
    step = lambda of: f"w - 0.5::double * ((w - list_reduce(list_prepend(w, {of}), lambda p, q: p + q) / (1 + len({of}))) + g)"
    near = "list_filter(es, lambda e: (w - 0.5::double * g - e) * (w - 0.5::double * g - e) < (w - e) * (w - e))"
    cases = "SELECT l_orderkey, qs[1] AS w, qs[1] - 0.5::double AS g, qs[2:] AS es FROM (SELECT l_orderkey, list(l_quantity / 50.0::double ORDER BY l_linenumber, l_partkey, l_suppkey, l_quantity) AS qs FROM lineitem WHERE l_quantity IS NOT NULL GROUP BY l_orderkey) o"
    return f"SELECT l_orderkey, len(ok)::int AS accepted, {step('ok')} AS windowed, {step('es')} AS open FROM (SELECT *, {near} AS ok FROM ({cases}) c) k"


def linear_sql(kind: str) -> str:
    """Full passes of a loss with a target: three recursive steps."""
    score = oracle.fold("list_transform([1, 2, 3, 4], lambda j: x[j] * w[j])")
    r = f"{score} - x[5]" if kind == "squares" else f"1.0::double / (1.0::double + exp(-({score}))) - x[5]"
    g = ", ".join(f"w[{j}] - 0.5::double * avg(r * x[{j}])" for j in range(1, 5))
    return f"WITH RECURSIVE pts AS MATERIALIZED ({_target_sql(kind)}), walk AS (SELECT 0 AS t, [0.0::double, 0.0, 0.0, 0.0] AS w UNION ALL SELECT t + 1, [{g}] FROM (SELECT k.t, k.w, p.x, {r} AS r FROM walk k, pts p WHERE k.t < 3) a GROUP BY t, w) SELECT (d - 1)::bigint AS dim, round(w[d], 6) AS value FROM walk, range(1, 5) s(d) WHERE t = 3"


def trace_measures(spark, sf_dir):
    """Convergence of gossip, silent and one-shot runs (rows only: seconds are measured)."""
    rows = experiments.convergence(_mix(spark), experiments.BASE.with_(steps=40, b=20), truth=S.truth(spark, 10, 10))
    return experiments.trace_frame(spark, rows)


def converged(spark, sf_dir):
    """The round in which each method's trace has converged (patience of one round; -1: not yet) and the error there."""
    t = reports.traces(spark, sf_dir)
    at = t.select("run_id").distinct().join(metrics.converged_at(t, 1), "run_id", "left").fillna(-1, ["round"])
    return at.join(metrics.final_error(t, 1), "run_id")


OWN: dict[str, Query] = {
    **{f"points_{n}": (lambda f: lambda spark, d: _scalars(f(spark, d)))(f) for n, f in S.SETS.items() if n != "doc128"},
    "points_doc128": lambda spark, d: S.doc_buckets(spark, d),
    "synth_truth": lambda spark, d: S.truth(spark, 4, 5).select("center", F.posexplode("mu").alias("dim", "value")),
    "synth_mix": lambda spark, d: _scalars(S.mixed(S.table(spark, d, "part").select(F.col("p_partkey").alias("id")), 3, 4)),
    "partition_exact": lambda spark, d: draws.assign_workers(S.line4(spark, d), 4, CFG.seed).select("sample_id", "worker", "pos"),
    "partition_report": partition_report,
    "local_order": lambda spark, d: draws.local_order(draws.assign_workers(S.line4(spark, d), 4, CFG.seed).drop("pos"), CFG.seed, 1).select("sample_id", "worker", "pos"),
    "minibatch_plan": lambda spark, d: draws.minibatches(S.line4(spark, d), CFG).select("worker", "round", "slot", "sample_id"),
    "minibatch_replace": lambda spark, d: draws.minibatches(S.line4(spark, d), CFG.with_(draw="replace")).select("worker", "round", "slot", "sample_id"),
    "recipients": lambda spark, d: event_mail(spark, d, MAIL["recipients"]),
    "blocks": lambda spark, d: draws.blocks(event_mail(spark, d, MAIL["blocks"]), MAIL["blocks"]),
    "inbox_torn": inbox_torn,
    "init_first": lambda spark, d: spark.createDataFrame(list(enumerate(_w(5, S.line4(spark, d)))), "block int, v array<double>").select("block", F.posexplode("v").alias("dim", "value")),
    "init_bounds": lambda spark, d: spark.createDataFrame(list(enumerate(descent.initial_state(S.line4(spark, d), CFG.with_(init="bounds")))), "block int, v array<double>").select("block", F.posexplode("v").alias("dim", "value")),
    "kmeans_assign": kmeans_assign, "kmeans_error": kmeans_error, "kmeans_grad_mean": kmeans_grad_mean, "kmeans_grad_one": kmeans_grad_one,
    "batch_1pass": _batch(1), "batch_10pass": _batch(10), "batch_tree": _batch(2, "tree"), "batch_native": _batch(2, "flat", descent.partial_sums), "batch_native_tree": _batch(2, "tree", descent.partial_sums),
    **{name: _run(name) for name in VARIANTS},
    "synchronous_superstep": lambda spark, d: descent.first(descent.gossip_sgd(S.line4(spark, d), CFG.with_(comm="sync"), engine="superstep").states),
    "library_kmeans": library_kmeans, **{f"{method}_{kind}": _linear_run(kind, method) for kind in ("squares", "logistic") for method in LINEAR}, **reports.QUERIES,
    "gossip_superstep": gossip_superstep, "gossip_resume": gossip_resume, "gossip_limit_equals_oneshot": gossip_limit_equals_oneshot, "mailbox_async": mailbox_async, "stream_foreach": stream_foreach,
    "least_squares_batch": _linear("squares"), "logistic_batch": _linear("logistic"),
    "window_accept_cases": window_accept_cases, "blend_cases": blend_cases, "settle_overwrite": _settled("overwrite"), "settle_torn": _settled("torn"), "settle_none": _settled("none"),
    "message_rates": message_rates, "race_counts": race_counts, "worker_spread": worker_spread, "center_error": center_error, "touched_samples": touched_samples, "converged_at": converged, "convergence_trace": trace_measures,
    "label_changes_except": label_changes, "topk_nearest": topk_nearest, "outliers": outliers, "antijoin_untouched": antijoin_untouched, "asof_mail": asof_mail, "codebook_histogram": codebook_histogram, "codebook_documents": codebook_documents,
    "state_round_trip": state_round_trip, "events_json": events_json, "quantiles": quantiles, "sketches": sketches, "udf_surface": udf_surface, "sinks_round_trip": sinks_round_trip,
    "tumbling_events": _windows("tumbling"), "sliding_events": _windows("sliding"), "session_events": _windows("session"),
    "tumbling_stream": _streamed_windows("tumbling"), "sliding_stream": _streamed_windows("sliding"), "session_stream": _streamed_windows("session"), "late_events": late_events,
    "scaling_table": lambda spark, d: experiments.strong_scaling(spark, S.line4(spark, d), 800, (2, 4)), "k_scaling": lambda spark, d: experiments.k_sweep(spark, S.line4(spark, d), (5, 20), experiments.BASE.with_(steps=5)),
    "repeat_summary": lambda spark, d: experiments.repeats(spark, _mix(spark), range(10), experiments.BASE.with_(steps=10, b=20), S.truth(spark, 10, 10)), "comm_overhead": lambda spark, d: experiments.overhead(spark, S.line4(spark, d), (50, 200), 2000),
    "message_sweep": lambda spark, d: experiments.message_sweep(spark, S.line4(spark, d), (2, 4, 8)), "final_compare": lambda spark, d: experiments.final_step(spark, _mix(spark)), "ablation": lambda spark, d: experiments.ablation(spark, _mix(spark), experiments.BASE.with_(steps=10)), "overlap_control": lambda spark, d: experiments.overlap(spark, 2000),
    **experiments.WORKLOADS,
}


def queries() -> dict[str, Query]:
    return OWN | {name: surround.query(text) for name, text in surround.BOTH.items()}


# --- SQL -------------------------------------------------------------------------------------------------

L4, E64 = oracle.POINTS["line4"], oracle.POINTS["emb64"]


def _near(points: str, k: int, dims: int) -> str:
    """Every sample with the distances ``ds`` to k initial prototypes ``w``."""
    return f"SELECT p.sample_id, p.x, z.w, list_transform(z.w, lambda c: {oracle.d2('p.x', 'c', dims)}) AS ds FROM ({points}) p, ({oracle.initial(points, CFG.with_(k=k))}) z"


def late_sql() -> str:
    """An event is late if its hour ends by the watermark: the newest event two files before, an hour less, in milliseconds."""
    hour = 3600 * 10**6
    place = f"[{', '.join(map(str, LATE))}][event_id // (((SELECT count(*) FROM events) + 3) // 4) + 1]"
    seen = f"(SELECT max(b.us) // 1000 * 1000 - {hour} FROM e b WHERE b.place <= a.place - 2)"
    return f"WITH e AS MATERIALIZED (SELECT epoch_us(ts) AS us, {place} AS place FROM events), p AS MATERIALIZED (SELECT place, {seen} AS mark FROM (SELECT DISTINCT place FROM e) a), k AS (SELECT us // {hour} * {hour} AS start_us, coalesce((us // {hour} + 1) * {hour} <= mark, false) AS late FROM e JOIN p USING (place)) SELECT start_us, count(*) FILTER (NOT late) AS n, count(*) FILTER (late) AS late FROM k GROUP BY start_us"


def oracle_sql() -> dict[str, str]:
    o, near4, near64 = oracle, _near(L4, 3, 4), _near(E64, 3, 64)
    unit = lambda *key: f"({o.int_(*key)} / 4294967296.0::double)"
    noise = "list_reduce(list_prepend(-6.0::double, list_transform([0,1,2,3,4,5,6,7,8,9,10,11], lambda i: ('0x' || substr(md5(concat_ws(':', 1, 'x', s, j, i)), 1, 8))::bigint / 4294967296.0::double)), lambda p, q: p + q)"
    center = o.int_(1, "'c'", "s") + " % 4"
    bounds = "('0x' || substr(md5('7:bounds:' || c || ':' || d), 1, 8))::bigint / 4294967296.0::double"
    hour = 3600 * 10**6
    out = {
        **{f"points_{n}": o.scalars(sql) for n, sql in o.POINTS.items()},
        "points_doc128": f"SELECT doc_id, {o.int_('token')} % 128 AS bucket, count(*) AS n FROM (SELECT doc_id, unnest(regexp_split_to_array(lower(text), '[^a-z0-9]+')) AS token FROM documents) t WHERE token <> '' GROUP BY ALL",
        "synth_truth": f"SELECT c::int AS center, j::int AS dim, {unit(1, chr(39) + 'mu' + chr(39), 'c', 'j')} * 10.0::double AS value FROM range(5) a(c), range(4) b(j)",
        "synth_mix": f"SELECT s::varchar AS sample_id, j::int AS dim, {unit(1, chr(39) + 'mu' + chr(39), center, 'j')} * 10.0::double + {noise} * 1.0::double AS value FROM (SELECT p_partkey AS s FROM part) a, range(3) b(j)",
        "partition_exact": f"SELECT sample_id, worker, pos FROM ({o.parted(L4, CFG)}) p",
        "partition_report": f"SELECT worker, count(*) AS n, max(pos) AS last_pos FROM ({o.parted(L4, CFG.with_(workers=7))}) p GROUP BY worker",
        "local_order": f"SELECT sample_id, worker, row_number() OVER (PARTITION BY worker ORDER BY {o.hex_(7, chr(39) + 'order' + chr(39), 1, 'sample_id')}, sample_id) - 1 AS pos FROM ({o.parted(L4, CFG)}) p",
        "minibatch_plan": f"SELECT worker, round, slot, sample_id FROM ({o.minibatches(L4, CFG)}) b",
        "minibatch_replace": f"SELECT worker, round, slot, sample_id FROM ({o.minibatches(L4, CFG.with_(draw='replace'))}) b",
        "recipients": o.sends(MAIL["recipients"], o.acting(MAIL["recipients"].workers)),
        "blocks": o.blocks(MAIL["blocks"], o.acting(MAIL["blocks"].workers)),
        "inbox_torn": o.inbox(MAIL["torn"], o.acting(MAIL["torn"].workers)),
        "init_first": f"SELECT (c - 1)::int AS block, (d - 1)::int AS dim, w[c][d] AS value FROM ({o.initial(L4, CFG.with_(k=5))}) z, range(1, 6) a(c), range(1, 5) b(d)",
        "init_bounds": f"SELECT c::int AS block, d::int AS dim, low + (high - low) * {bounds} AS value FROM (SELECT dim AS d, min(value) AS low, max(value) AS high FROM ({o.scalars(L4)}) s GROUP BY dim) v, range(3) r(c)",
        "kmeans_assign": f"SELECT sample_id, (list_position(ds, list_min(ds)) - 1)::int AS cluster FROM ({near64}) n",
        "kmeans_error": f"SELECT round(sum(list_min(ds) * 0.5), 6) AS total, round(avg(list_min(ds) * 0.5), 9) AS mean FROM ({near4}) n",
        "kmeans_grad_mean": f"SELECT (c - 1)::int AS block, (d - 1)::int AS dim, round(sum(CASE WHEN near = c THEN w[c][d] - x[d] ELSE 0 END) / count(*) + 1.7e-11, 9) AS value FROM (SELECT *, list_position(ds, list_min(ds)) AS near FROM ({near4}) n) m, range(1, 4) a(c), range(1, 5) b(d) GROUP BY c, d",
        "kmeans_grad_one": f"SELECT sample_id, (near - 1)::int AS block, (d - 1)::int AS dim, w[near][d] - x[d] AS value FROM (SELECT *, list_position(ds, list_min(ds)) AS near FROM ({near4}) n) m, range(1, 5) b(d)",
        "batch_1pass": o.batch(L4, CFG.with_(eps=1.0, steps=1), 4), "batch_10pass": o.batch(L4, CFG.with_(eps=1.0, steps=10), 4), "batch_tree": o.batch(L4, CFG.with_(eps=1.0, steps=2), 4),
        **{name: o.run(L4, CFG.with_(**changes).within(), 4, o.FIRST if final == "first" else o.AVERAGE) for name, (changes, final) in VARIANTS.items()},
        "synchronous_superstep": o.run(L4, CFG.with_(comm="sync"), 4, o.FIRST),
        "gossip_limit_equals_oneshot": f"SELECT method, block, dim, value FROM ({o.run(L4, CFG.with_(b=1, steps=20, comm='silent'), 4, o.AVERAGE)}) v, (VALUES ('gossip'), ('oneshot')) m(method)",
        "window_accept_cases": "SELECT id::int AS id, coalesce(abs(1.5 - e) < abs(2.0 - e), false) AS accepted FROM (VALUES (0, 1.0), (1, 1.5), (2, 0.0), (3, 3.0), (4, 2.0), (5, 1.75), (6, NULL)) t(id, e)",
        "blend_cases": blend_sql(),
        **{f"settle_{race}": o.settled(MAIL["settled"].with_(race=race), o.acting(MAIL["settled"].workers)) for race in ("overwrite", "torn", "none")},
        "message_rates": o.run(L4, CFG, 4, f"SELECT worker, sent, received, good, round(sent / {CFG.steps}.0::double, 6) AS sent_rate, round(received / {CFG.steps}.0::double, 6) AS received_rate, round(good / {CFG.steps}.0::double, 6) AS good_rate FROM done JOIN (SELECT sender AS worker, count(*) AS sent FROM ({o.sends(CFG)}) m GROUP BY 1) s USING (worker)"),
        "race_counts": race_counts_sql(), "label_changes_except": label_changes_sql(), "least_squares_batch": linear_sql("squares"), "logistic_batch": linear_sql("logistic"),
        **{f"{method}_{kind}": o.run(_target_sql(kind), _linear_cfg(kind, method), 4, f"SELECT block, dim, round(value, 9) AS value FROM ({o.FIRST if final == 'first' else o.AVERAGE}) v") for kind in ("squares", "logistic") for method, (_, final) in LINEAR.items()},
        "worker_spread": o.run(L4, CFG, 4, f"SELECT block, dim, round(stddev_pop(value), 9) AS spread FROM ({o.ALL_STATES}) s GROUP BY block, dim"),
        "center_error": f"SELECT center::int AS center, min(sqrt({o.d2('mu', 'w[c]', 4)})) AS distance FROM (VALUES (0, [0.2::double, 0.2, 0.2, 0.2]), (1, [0.8, 0.5, 0.5, 0.5]), (2, [0.5, 0.9, 0.1, 0.7])) t(center, mu), ({o.initial(L4, CFG.with_(k=5))}) z, range(1, 6) r(c) GROUP BY center",
        "touched_samples": " UNION ALL ".join([f"SELECT '{name}' AS method, {CFG.steps * cfg.workers * cfg.b}::bigint AS touched, count(*) AS counted FROM ({o.minibatches(L4, cfg)}) b" for name, cfg in TOUCHING.items()] + [f"SELECT 'batch', count(*) * {CFG.steps}, count(*) * {CFG.steps} FROM ({L4}) p"]),
        "converged_at": f"WITH t AS MATERIALIZED ({reports.traces_sql()}), c AS (SELECT run_id, min(round) AS round FROM (SELECT run_id, round, min(error) OVER (o ROWS UNBOUNDED PRECEDING) AS best, min(error) OVER (o ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS before FROM t WINDOW o AS (PARTITION BY run_id ORDER BY round)) w WHERE before IS NOT NULL AND best >= before GROUP BY run_id) SELECT e.run_id, coalesce(c.round, -1)::int AS round, coalesce((SELECT error FROM t WHERE t.run_id = c.run_id AND t.round = c.round), e.error) AS error FROM (SELECT run_id, max_by(error, round) AS error FROM t GROUP BY run_id) e LEFT JOIN c USING (run_id)",
        "topk_nearest": f"SELECT block, place, sample_id, d2 FROM (SELECT (c - 1)::int AS block, sample_id, ds[c] AS d2, (row_number() OVER (PARTITION BY c ORDER BY ds[c], sample_id))::int AS place FROM ({near64}) n, range(1, 4) r(c)) t WHERE place <= 10",
        "outliers": f"SELECT sample_id, list_min(ds) AS d2 FROM ({near64}) n ORDER BY d2 DESC, sample_id LIMIT 20",
        "antijoin_untouched": f"SELECT count(*) AS untouched FROM ({L4}) p ANTI JOIN ({o.minibatches(L4, CFG)}) b USING (sample_id)",
        "asof_mail": f"SELECT r.sender AS worker, r.sent_round AS t, m.sender, m.sent_round FROM ({o.acting(CFG.workers)}) r ASOF JOIN (SELECT recipient, sent_round, max(sender) AS sender FROM ({o.sends(CFG, f'SELECT * FROM ({o.acting(CFG.workers)}) a WHERE (sent_round + 1) % 2 = 0')}) s GROUP BY ALL) m ON m.recipient = r.sender AND r.sent_round >= m.sent_round",
        "codebook_histogram": f"SELECT label AS object, (list_position(ds, list_min(ds)) - 1)::int AS cluster, count(*) AS n FROM ({near64}) n JOIN embeddings ON vec_id::varchar = sample_id GROUP BY ALL",
        "codebook_documents": o.run(o.documents(), CODEBOOK, 128, f"SELECT lang AS object, cluster, count(*) AS n FROM (SELECT sample_id, (list_position(ds, list_min(ds)) - 1)::int AS cluster FROM (SELECT p.sample_id, list_transform(z.w, lambda c: {o.d2('p.x', 'c', 128)}) AS ds FROM pts p, (SELECT w FROM done WHERE worker = 0) z) a) b JOIN documents d ON d.doc_id::varchar = sample_id GROUP BY ALL"),
        "events_json": "SELECT event_type, ((props->>'$.k')::int // 10)::int AS bin, count(*) AS n FROM events GROUP BY ALL",
        "quantiles": "SELECT l_returnflag, round(quantile_cont(l_extendedprice, 0.5), 4) AS median, round(quantile_cont(l_extendedprice, 0.9), 4) AS p90 FROM lineitem GROUP BY 1",
        "udf_surface": f"SELECT corner, far AS expression, far AS arrow, far AS sql, far AS rows FROM (SELECT floor(x[1] * 4)::int AS corner, max({o.d2('x', '[0.5::double, 0.5, 0.5, 0.5]', 4)}) AS far FROM ({L4}) p GROUP BY 1) f",
        "sinks_round_trip": o.run(L4, CFG, 4, f"SELECT worker, block, dim, value, kind FROM ({o.ALL_STATES}) s, (VALUES ('parquet'), ('orc'), ('json'), ('csv')) k(kind)"),
        "tumbling_events": f"SELECT event_type, epoch_us(ts) // {hour} * {hour} AS start_us, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL",
        "sliding_events": f"SELECT event_type, epoch_us(ts) // {hour // 2} * {hour // 2} - k * {hour // 2} AS start_us, count(*) AS n, round(sum(value), 4) AS total FROM events, range(4) r(k) GROUP BY ALL",
        "session_events": f"SELECT user_id, min(us) AS start_us, max(us) + {hour // 2} AS end_us, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY us ROWS UNBOUNDED PRECEDING) AS s FROM (SELECT user_id, epoch_us(ts) AS us, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) < {hour // 2} THEN 0 ELSE 1 END AS fresh FROM events) a) b GROUP BY user_id, s",
    }
    out |= {f"{kind}_stream": out[f"{kind}_events"] for kind in ("tumbling", "sliding", "session")} | {"late_events": late_sql()}
    out["batch_native"] = out["batch_native_tree"] = out["batch_tree"]
    for same in ("gossip_superstep", "gossip_resume", "state_round_trip"):
        out[same] = out["gossip_full"]
    return out | reports.oracle_sql() | {name: surround.duck_text(text) for name, text in surround.BOTH.items()}


