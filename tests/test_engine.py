"""The descent engine: hand cases, invariants, parity of engines and layouts, and every query against DuckDB."""

import os

import duckdb
import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from gossamer.config import DescentConfig, StopRule, scale_eps
from gossamer.functions import arrays as A
from gossamer.functions import kernel
from gossamer.operators import descent, draws, mail, metrics
from gossamer.plans import catalog, experiments
from gossamer.sources import points as S

CFG = DescentConfig()
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck(small):
    con = duckdb.connect()
    for t in TABLES:
        path = f"{small}/{t}.parquet"
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{path}{'/*.parquet' if os.path.isdir(path) else ''}'")
    return con


@pytest.fixture(scope="module")
def line4(spark, small):
    return S.line4(spark, small).persist()


def plain(frame):
    def one(v):
        if v is None or v is pd.NA or v is pd.NaT or v != v:
            return "~"
        return repr(float(v)) if isinstance(v, (float, np.floating)) else str(v)

    columns = sorted(frame.columns)
    return columns, sorted(tuple(map(one, r)) for r in frame[columns].itertuples(index=False, name=None))


@pytest.mark.parametrize("name", sorted(catalog.oracle_sql()))
def test_query_equals_sql(spark, small, duck, name):
    assert plain(catalog.queries()[name](spark, small).toPandas()) == plain(duck.execute(catalog.oracle_sql()[name]).df())


def states(result):
    return {r.worker: (r.w, r.sent, r.received, r.good) for r in result.states.collect()}


@pytest.mark.parametrize("changes", [{}, {"window": False, "fanout": 2, "race": "none"}, {"buffers": 2, "fanout": 3, "race": "torn", "block_frac": 0.5, "max_age": 3}, {"comm": "silent"}, {"comm": "sync"}, {"comm": "sync", "fanout": 2, "race": "none"}, {"window_scope": "block", "blend_gain": "unit"}])
def test_fold_and_superstep_agree(line4, changes):
    cfg = CFG.with_(steps=4, **changes)
    assert states(descent.gossip_sgd(line4, cfg)) == states(descent.gossip_sgd(line4, cfg, engine="superstep"))


def test_layout_does_not_matter(line4):
    runs = [states(descent.gossip_sgd(line4.repartition(n), CFG)) for n in (1, 7)]
    assert runs[0] == runs[1] == states(descent.gossip_sgd(line4, CFG))


def test_silent_single_samples_are_oneshot(line4):
    cfg = CFG.with_(b=1, steps=30, comm="silent")
    assert {k: v[0] for k, v in states(descent.oneshot_sgd(line4, cfg, engine="arrow")).items()} == {k: v[0] for k, v in states(descent.gossip_sgd(line4, cfg)).items()}


def test_stretch_and_stop(line4):
    cfg = CFG.with_(stretch=4, comm="silent")
    assert states(descent.gossip_sgd(line4, cfg, engine="superstep")) == states(descent.gossip_sgd(line4, CFG.with_(comm="silent")))
    talking = states(descent.gossip_sgd(line4, CFG.with_(stretch=4, window=False), engine="superstep"))
    assert sum(v[2] for v in talking.values()) > 0  # letters of the first stretch are read in the second
    with pytest.raises(ValueError):
        descent.gossip_sgd(line4, CFG.with_(comm="sync", stretch=2), engine="superstep")
    with pytest.raises(ValueError):
        descent.gossip_sgd(line4, CFG.with_(comm="sync"), engine="mailbox")
    with pytest.raises(ValueError):
        descent.gossip_sgd(line4, CFG.with_(stop=StopRule(target_error=0.1)), engine="fold")
    for engine in ("fold", "superstep"):  # the samples of a stop rule end a run on every engine
        assert states(descent.gossip_sgd(line4, CFG.with_(stop=StopRule(max_touched=64)), engine=engine)) == states(descent.gossip_sgd(line4, CFG.with_(steps=2)))
    at_once = descent.gossip_sgd(line4, CFG.with_(stop=StopRule(max_seconds=0.0)), engine="fold")
    assert {w: v[0] for w, v in states(at_once).items()} == {w: v[0] for w, v in states(descent.gossip_sgd(line4, CFG.with_(steps=1))).items()}
    r = descent.batch_descent(line4, CFG.with_(eps=1.0, steps=9, stop=StopRule(max_touched=12_000)))
    assert len(r.trace) == 2 and r.trace[0][3] > r.trace[1][3]
    early = descent.gossip_sgd(line4, CFG.with_(stop=StopRule(max_touched=64)), engine="superstep", evaluate=line4)
    assert len(early.trace) == 2


def test_batch_error_never_rises(line4):
    errors = [t[3] for t in descent.batch_descent(line4, CFG.with_(eps=1.0, steps=6)).trace]
    assert errors == sorted(errors, reverse=True)


def test_prototype_hand_case():
    x, w = np.asarray([[0.0], [1], [4], [5]]), np.asarray([[0.0], [4]])
    assert kernel.gradient(x, w).tolist() == [[-0.25], [-0.25]]
    assert kernel.loss(x, w) * 4 == 1.0 and kernel.loss(x, w - kernel.gradient(x, w)) * 4 == 0.625


def test_window_and_blend_twins(spark):
    rng = np.random.default_rng(0)
    rows, truth = [], []
    for i in range(40):
        w, g = rng.normal(size=(3, 2)), rng.normal(size=(3, 2))
        es = [rng.normal(size=(3, 2)) for _ in range(i % 4)]
        have = [np.asarray([True, bool(rng.integers(2)), True]) for _ in es]
        rows.append((i, w.tolist(), g.tolist(), [[v if h else None for v, h in zip(e.tolist(), hv, strict=True)] for e, hv in zip(es, have, strict=True)]))
        truth.append(kernel.step(w, g, list(zip(es, have, strict=True)), 0.5)[0].tolist())
    df = spark.createDataFrame(rows, "i int, w array<array<double>>, g array<array<double>>, es array<array<array<double>>>")
    got = df.withColumn("ok", F.filter("es", lambda e: A.window_accept("w", "g", 0.5, e))).select("i", A.blended("w", "g", "ok").alias("s")).orderBy("i").collect()
    assert [r.s for r in got] == truth


def test_message_counts(spark):
    cfg = CFG.with_(workers=6, fanout=2, steps=10)
    sent = draws.sends(spark, cfg).collect()
    assert len(sent) == 6 * 2 * 10 and all(r.sender != r.recipient for r in sent)
    assert all(len({r.recipient for r in sent if (r.sender, r.sent_round) == key}) == 2 for key in {(r.sender, r.sent_round) for r in sent})
    box = draws.inbox(spark, cfg).select("recipient", "round", "buffer", "sender").distinct()
    assert box.groupBy("recipient", "round", "buffer").count().where("count > 1").count() == 0


@pytest.mark.parametrize("changes", [{}, {"fanout": 3, "buffers": 2, "race": "torn", "block_frac": 0.5}, {"race": "none", "fanout": 2, "max_age": 3}, {"threads": 3, "scope": "other_node", "delay": "geometric", "max_age": 4}, {"comm_every": 3}, {"comm": "silent"}, {"consume": False, "buffers": 2, "fanout": 2, "max_age": 2}, {"consume": False, "race": "torn", "fanout": 3, "block_frac": 0.4, "max_age": 3}])
def test_mail_planned_in_a_task_equals_the_table(spark, changes):
    cfg = CFG.with_(workers=6, steps=9, k=5, **changes)
    want: dict = {}
    for r in draws.inbox(spark, cfg).collect():
        want.setdefault((r.recipient, r["round"]), {}).setdefault((r.buffer, r.sent_round, r.sender), []).append(r.block)
    assert mail.inbox(cfg) == {at: [(s, t, sorted(b)) for (_, t, s), b in sorted(of.items())] for at, of in want.items()}
    sent = draws.sends(spark, cfg).where("sent_round < 7").groupBy("sender").count().collect()
    assert {r["count"] for r in sent} == {mail.sent_before(cfg, 7)} - {0}


def test_many_runs_in_one_job(line4, spark):
    cfgs = {f"{c}-{s}": CFG.with_(seed=s, comm=c, steps=3) for s in (1, 2) for c in ("gossip", "silent")}
    runs = {name: (cfg, descent.initial_state(line4, cfg)) for name, cfg in cfgs.items()}
    parts = [draws.minibatches(line4, cfg).withColumn("run", F.lit(name)) for name, cfg in cfgs.items()]
    got = descent.walked(parts[0].unionByName(parts[1]).unionByName(parts[2]).unionByName(parts[3]), runs).collect()
    for name, (cfg, w0) in runs.items():
        assert {r.worker: (r.w, r.sent, r.received, r.good) for r in got if r.run == name} == states(descent.gossip_sgd(line4, cfg, w0))


def test_partition_is_exact(line4):
    parted = draws.assign_workers(line4, 7, 3)
    sizes = {r.worker: r["count"] for r in parted.groupBy("worker").count().collect()}
    m = line4.count()
    assert set(sizes.values()) == {m // 7} and m - sum(sizes.values()) == metrics.partition_report(m, 7)[1]
    cut = draws.assign_workers(line4, 7, 3, budget=70)
    assert cut.count() == 70 and cut.exceptAll(parted).count() == 0


def test_samples_stay_with_the_task_that_reads_them(line4):
    cfg = CFG.with_(partition="scan", workers=3, steps=4)
    held = line4.repartition(6).persist()
    drawn = draws.minibatches(held, cfg).collect()
    assert len(drawn) == len({r.sample_id for r in drawn}) == 3 * 4 * cfg.b
    assert {(r.worker, r["round"], r.slot) for r in drawn} == {(w, t, s) for w in range(3) for t in range(4) for s in range(cfg.b)}
    where = {r.sample_id: r.worker for r in draws.scanned_workers(held, 3).collect()}
    assert all(where[r.sample_id] == r.worker for r in drawn)
    assert len(states(descent.gossip_sgd(held, cfg))) == 3
    held.unpersist()


def test_epochs_repeat_every_sample(spark):
    points = spark.createDataFrame([(str(i), [float(i)]) for i in range(10)], "sample_id string, x array<double>")
    drawn = draws.minibatches(points, CFG.with_(workers=2, b=2, steps=5)).collect()
    assert len(drawn) == 20 and sorted(r.sample_id for r in drawn) == sorted([str(i) for i in range(10)] * 2)


def test_settings_are_checked(line4):
    with pytest.raises(ValueError):
        descent.gossip_sgd(line4, CFG.with_(consume=False), engine="superstep")
    for wrong in ({"partition": "x"}, {"draw_from": "global"}, {"partition": "hash", "draw": "replace"}, {"consume": False, "race": "none"}, {"eps": 0}, {"workers": 1}, {"fanout": 4}, {"block_frac": 0}, {"race": "x"}):
        with pytest.raises(ValueError):
            CFG.with_(**wrong).validate()
    with pytest.raises(ValueError):
        CFG.with_(k=10).validate(5)
    assert CFG.with_(eps=2.0, buffers=4).pull > 1 and scale_eps(0.1, 4, "sqrt") == 0.2


def test_bad_samples(spark):
    df = spark.createDataFrame([("a", [1.0]), ("b", None), ("c", [float("nan")]), ("d", [None])], "sample_id string, x array<double>")
    assert [r.sample_id for r in S.checked(df).collect()] == ["a"]
    with pytest.raises(ValueError):
        S.checked(df, "raise")


def test_budget_is_cut_before_samples_move(spark, small):
    """The buckets' join lies below the shuffle of samples; what is read beside it has no samples."""
    plan = draws.minibatches(S.line4(spark, small), CFG, 6000)._jdf.queryExecution().optimizedPlan().toString().splitlines()
    depth = lambda word: [len(line) - len(line.lstrip(" :+-")) for line in plan if word in line]
    window = next(i for i, line in enumerate(plan) if "Window [row_number" in line)
    joins = [i for i, line in enumerate(plan) if "Join Inner" in line and "__bucket" in line]
    assert joins and min(joins) > window and any("__before" in line and "< 256" in line for line in plan), plan
    assert depth("CartesianProduct") == []


def test_what_a_superstep_reads_does_not_grow(line4, monkeypatch):
    scans = []
    plain = descent.settled

    def counted(df, name, by=None):
        if name == "states":
            scans.append(df._jdf.queryExecution().optimizedPlan().toString().count("Relation ["))
        return plain(df, name, by)

    monkeypatch.setattr(descent, "settled", counted)
    descent.gossip_sgd(line4, CFG.with_(steps=7), engine="superstep")
    assert len(scans) == 7 and scans[6] == scans[4] <= scans[2] + 1


def test_matching_of_any_size():
    rng = np.random.default_rng(4)
    from itertools import permutations

    for n, m in ((1, 1), (3, 3), (3, 5), (6, 6)):
        for _ in range(20):
            cost = rng.random((n, m))
            got = metrics.least_matching(cost)
            assert len(set(got)) == n and abs(cost[range(n), got].sum() - min(cost[range(n), list(p)].sum() for p in permutations(range(m), n))) < 1e-12
    mu = rng.random((40, 3))
    assert metrics.center_error(mu, mu[rng.permutation(40)], "hungarian") == 0.0


def test_converged_error_and_speedup(spark):
    long = spark.createDataFrame([("a", r, e) for r, e in enumerate((9.0, 5.0, 4.0, 4.0, 4.0, 4.0))] + [("b", r, 5.0 - r / 2) for r in range(6)], "run_id string, round int, error double")
    assert {r.run_id: r["round"] for r in metrics.converged_at(long, 3).collect()} == {"a": 5}
    t = spark.createDataFrame([("a", r, 10 * r, float(r), e) for r, e in enumerate((9.0, 5.0, 4.0, 4.0, 4.0, 4.5))] + [("b", r, 20 * r, 2.0 * r, 6.0 - r) for r in range(6)], "run_id string, round int, touched long, secs double, error double")
    assert {r.run_id: r.error for r in metrics.final_error(t, 3).collect()} == {"a": 4.5, "b": 1.0}
    assert {r.run_id: (r.fewer, r.faster) for r in metrics.speedup_to_error(t, 4.0, "b").collect()} == {"a": (2.0, 2.0), "b": (1.0, 1.0)}


def test_warm_start_and_trace_of_all_rounds(line4, spark):
    cfg = CFG.with_(steps=3)
    done = descent.gossip_sgd(line4, cfg)
    assert states(descent.gossip_sgd(line4, cfg, done.state())) == states(descent.gossip_sgd(line4, cfg, descent.as_array(done.state()).tolist()))
    w0 = descent.initial_state(line4, cfg)
    walked = descent.traced(draws.minibatches(line4, cfg), cfg, w0).collect()
    history, trace = descent.supersteps(draws.minibatches(line4, cfg), cfg, w0, keep_all=True)
    assert {(r["round"], r.worker): r.w for r in walked} == {(r["round"], r.worker): r.w for r in history.collect()}
    last = [r for r in walked if r["round"] == 3]
    assert trace[-1][4:] == (sum(r.sent for r in last), sum(r.received for r in last), sum(r.good for r in last))


def test_oneshot_streams_what_the_fold_engine_leaves(line4, monkeypatch):
    cfg = CFG.with_(b=1, steps=30)
    want = {k: v[0] for k, v in states(descent.oneshot_sgd(line4, cfg)).items()}
    monkeypatch.setattr(descent, "FOLD_MOST", 10)
    assert {k: v[0] for k, v in states(descent.oneshot_sgd(line4, cfg)).items()} == want
    with pytest.raises(ValueError):
        descent.gossip_sgd(line4, CFG, engine="fold")
    assert len(states(descent.gossip_sgd(line4, CFG.with_(steps=2)))) == 4  # by supersteps


def test_odd_samples(spark):
    rows = [("a", [1.0, 2.0], 1), ("a", [1.0, 2.0], 1), ("b", [3.0, 4.0], 2), (None, [5.0, 6.0], 3), ("c", None, 4), ("d", [1.0], 5), ("e", [float("inf"), 1.0], 6), ("f", [None, 1.0], 7), ("g", [], 8), ("h", [2.0, 2.0], 9)]
    df = spark.createDataFrame(rows, "sample_id string, x array<double>, worker int")
    fine = S.checked(df)
    assert fine.count() == 5 and fine.columns == df.columns
    points = fine.select("sample_id", "x")
    r = descent.gossip_sgd(points, CFG.with_(k=2, b=1, steps=2, workers=2))
    assert len(states(r)) == 2 and all(np.isfinite(v[0]).all() for v in states(r).values())
    assert draws.assign_workers(points, 2, 1).count() == 4 and sum(x.n for x in descent.bulk_sums(points, [[0.0, 0.0], [4.0, 4.0]]).collect()) == 5
    none = points.limit(0)
    assert S.checked(none).count() == 0 and draws.assign_workers(none, 2, 1).count() == 0 and descent.bulk_sums(none, [[0.0, 0.0]]).count() == 0
    for init in ("first", "sample", "bounds", "zeros"):
        with pytest.raises(ValueError):
            descent.initial_state(none, CFG.with_(init=init))
    ties = kernel.gradient(np.asarray([[1.0]]), np.asarray([[0.0], [2.0]]))
    assert ties.tolist() == [[-1.0], [0.0]]  # the lowest of equally near prototypes


def test_measures():
    mu, w = np.asarray([[0.0, 0], [3, 4]]), np.asarray([[3.0, 4], [0, 1]])
    assert metrics.center_error(mu, w) == metrics.center_error(mu, w, "greedy") == metrics.center_error(mu, w, "hungarian") == 0.5
    assert metrics.message_bytes(CFG, 4) == 4 * 8 * 3 * 4 * 8 and metrics.window_cost(CFG, 4) == 3.0


def test_gossip_is_not_worse_than_silent(spark):
    """Ten seeds on a planted mixture: worse only if by over two standard errors and five per cent."""
    points = S.mix(spark, 4, 2000, 5, tasks=4).persist()
    rows = []
    for seed in range(10):
        rows += experiments.convergence(points, DescentConfig(k=5, b=20, steps=20, workers=4, eps=1.0, seed=seed), ("gossip", "silent"))
    last = {}
    for run, t, _, _, e in rows:
        last[run] = (t, e)
    d = np.asarray([last[f"gossip-{s}"][1] - last[f"silent-{s}"][1] for s in range(10)])
    base = np.mean([last[f"silent-{s}"][1] for s in range(10)])
    assert not (d.mean() > 2 * d.std(ddof=1) / 10**0.5 and d.mean() > 0.05 * base)


def test_stream_replay_equals_batches(spark, small):
    got = {(r.block, r.dim): r.value for r in catalog.queries()["stream_foreach"](spark, small).collect()}
    from gossamer.streaming import stream

    events = S.table(spark, small, "events")
    cfg, each = CFG.with_(workers=2), -(-events.count() // 4)
    w = descent.initial_state(S.evt3(spark, small), cfg)
    points = S.evt3(spark, small).withColumn("part", F.floor(F.col("sample_id").cast("long") / each))
    for part in range(4):
        own = points.where(F.col("part") == part).select("sample_id", "x")
        rounds = stream.slice_rounds(own, cfg)
        assert rounds.count() == own.count()  # no sample is left out
        w = stream.advanced(own, cfg, w)
    assert {(c, j): v for c, row in enumerate(w) for j, v in enumerate(row)} == got
    assert stream.advanced(points.limit(0).select("sample_id", "x"), cfg, w) == w
    assert catalog.queries()["mailbox_async"](spark, small).count() == 2


def test_errors_of_a_run_are_over_all_points(spark):
    points = S.mix(spark, 3, 3000, 4, tasks=3)
    cfg = DescentConfig(k=4, b=5, steps=3, workers=2, eps=1.0)
    rows = experiments.convergence(points, cfg, ("silent",), S.truth(spark, 3, 4))
    w = descent.as_array(descent.gossip_sgd(points, cfg.with_(comm="silent")).state())
    assert len(rows) == 3 and abs(rows[-1][4] - descent.error_of(points, w.tolist())) < 1e-9
    assert abs(rows[-1][5] - metrics.center_error(np.asarray([r.mu for r in S.truth(spark, 3, 4).orderBy("center").collect()]), w)) < 1e-12


def test_oneshot_ends_in_the_average_of_its_workers(spark, monkeypatch):
    points = S.mix(spark, 3, 600, 4, tasks=2)
    cfg = experiments.single(DescentConfig(k=4, b=5, steps=3, workers=2, eps=1.0))
    states = descent.oneshot_sgd(points, cfg).states
    want = {m: descent.error_of(points, descent.as_array(of(states)).tolist()) for m, of in (("oneshot", descent.average), ("oneshot_first", descent.first))}
    assert abs(want["oneshot"] - want["oneshot_first"]) > 1e-6
    for m, final in (("oneshot", "average"), ("oneshot_first", "first")):
        r = experiments.one_run(points, cfg, m)
        assert abs(r["error"] - want[m]) < 1e-9 and r["final"] == final
    traced = {r[0].split("-")[0]: r[4] for r in experiments.convergence(points, DescentConfig(k=4, b=5, steps=3, workers=2, eps=1.0), ("oneshot", "oneshot_first"))}
    assert all(abs(traced[m] - want[m]) < 1e-9 for m in want)
    seen = []
    monkeypatch.setattr(experiments, "one_run", lambda points, cfg, method: seen.append(metrics.touched(method, cfg.steps, 0, cfg.workers, cfg.b)) or {"method": method, "k": cfg.k, "secs": 1.0})
    monkeypatch.setattr(experiments, "_frame", lambda spark, rows: spark.createDataFrame(rows, "method string, k int, secs double"))
    experiments.k_sweep(spark, points, (5, 20), experiments.BASE.with_(steps=5))
    assert seen == [1000] * 4


def test_screened_nearest_is_the_plain_one():
    """Bit for bit, ties, far offsets and values that are not finite included."""
    rng = np.random.default_rng(5)
    for n, d, k, shift, scale in ((3000, 4, 1000, 0.0, 1.0), (500, 64, 100, 0.0, 1.0), (400, 3, 40, 1e9, 1e-3), (400, 2, 50, 0.0, 1e25), (7, 1, 30, 0.0, 1.0), (0, 4, 40, 0.0, 1.0)):
        x = np.round(rng.random((n, d)), 2) * scale + shift  # many equal distances
        w = np.round(rng.random((k, d)), 2) * scale + shift
        w[k // 2] = w[0]
        if n:
            x[0], x[-1] = w[0], np.nan
        d2 = kernel.distances(x, w)
        near, least = kernel.nearest(x, w)
        assert near.tolist() == d2.argmin(axis=1).tolist()
        assert np.array_equal(least, d2[np.arange(n), near], equal_nan=True)


def test_foremost_samples_are_all_that_runs_draw(line4):
    m, near = line4.count(), draws.foremost(line4, CFG.seed, 256)
    assert near.count() == 256
    for changes in ({}, {"workers": 2}, {"workers": 1, "b": 1, "steps": 256, "comm": "silent"}):
        cfg = CFG.with_(**changes)
        assert sorted(draws.minibatches(near, cfg, m).collect()) == sorted(draws.minibatches(line4, cfg, m).collect())


def test_scaling_passes_over_the_points_once_for_all_errors(spark, monkeypatch):
    points = S.mix(spark, 3, 600, 4, tasks=2)
    calls, plain = [], descent.errors_of
    monkeypatch.setattr(descent, "errors_of", lambda points, states, *more: calls.append(len(states)) or plain(points, states, *more))
    got = experiments.strong_scaling(spark, points, 200, (1, 2), experiments.BASE.with_(k=4, b=10), ("gossip", "oneshot", "batch")).collect()
    assert calls == [6] and len(got) == 6
    w = descent.as_array(descent.oneshot_sgd(points, experiments.single(DescentConfig(k=4, b=10, steps=10, workers=2, eps=1.0))).state())
    assert {r.error for r in got if r.method == "oneshot" and r.workers == 2} == {plain(points, [w])[0]}


def test_newest_message_is_no_later_than_its_read(spark):
    reads = spark.createDataFrame([(0, 1), (0, 4), (0, 5), (0, 9), (1, 3)], "worker int, t int")
    sent = spark.createDataFrame([(1, 4, 0), (2, 4, 0), (3, 6, 0), (0, 4, 1)], "sender int, sent_round int, recipient int")
    assert sorted(map(tuple, draws.newest(reads, sent).collect())) == [(0, 4, 2, 4), (0, 5, 2, 4), (0, 9, 3, 6)]


def test_blend_hand_case(spark, tmp_path):
    """Orders of one to three items: own state 1.0 and a step to 0.5; of the others 0.5 lies ahead and 1.5 behind."""
    rows = [(1, 1, 1, 1, 50.0), (2, 2, 1, 1, 25.0), (2, 1, 1, 1, 50.0), (3, 1, 1, 1, 50.0), (3, 2, 1, 1, 25.0), (3, 3, 1, 1, 75.0), (4, 1, 1, 1, None)]
    spark.createDataFrame(rows, "l_orderkey long, l_linenumber int, l_partkey long, l_suppkey long, l_quantity double").write.parquet(f"{tmp_path}/lineitem.parquet")
    got = {r.l_orderkey: (r.accepted, r.windowed, r.open) for r in catalog.queries()["blend_cases"](spark, str(tmp_path)).collect()}
    assert got == {1: (0, 0.75, 0.75), 2: (1, 0.625, 0.625), 3: (1, 0.625, 0.75)}


def test_settled_mail_hand_case(spark):
    sent = spark.createDataFrame([(0, 3, 2, 5, 0, 0), (0, 3, 2, 5, 0, 1), (1, 4, 2, 5, 0, 1)], "sender int, sent_round int, recipient int, due_round int, buffer int, block int")
    got = {race: sorted((r.block, r.sender) for r in draws.settle(sent, race).collect()) for race in ("overwrite", "torn", "none")}
    assert got == {"overwrite": [(1, 1)], "torn": [(0, 0), (1, 1)], "none": [(0, 0), (1, 0), (1, 1)]}


@pytest.mark.parametrize("name, table", [("asof_mail", "events"), ("blend_cases", "lineitem"), ("blocks", "events"), ("close_centres", "lineitem"), ("inbox_torn", "events"), ("race_counts", "events"), ("recipients", "events"), ("recursive_steps", "lineitem"), ("settle_none", "events"), ("settle_overwrite", "events"), ("settle_torn", "events"), ("synth_mix", "part")])
def test_query_reads_its_table(spark, small, tmp_path, name, table):
    """On a quarter of its table's rows a query gives other rows than on all."""
    for t in TABLES:
        if t != table:
            os.symlink(f"{small}/{t}.parquet", f"{tmp_path}/{t}.parquet")
    key = {"events": "user_id", "lineitem": "l_orderkey", "part": "p_partkey"}[table]
    spark.read.parquet(f"{small}/{table}.parquet").where(F.col(key) % 4 == 1).where("true" if table != "lineitem" else "l_quantity < 30").write.parquet(f"{tmp_path}/{table}.parquet")
    few, whole = (plain(catalog.queries()[name](spark, d).toPandas()) for d in (str(tmp_path), small))
    assert whole[1] and few != whole


def test_document_vectors_are_built_once_a_document(spark, tmp_path):
    """No expression looks buckets up one by one, for which a document's counts would be built again each time."""
    spark.createDataFrame([(1, "a A b"), (2, "..."), (3, None), (4, "b"), (None, "a")], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    points = S.doc128(spark, str(tmp_path))
    assert "lambdafunction" not in points._jdf.queryExecution().optimizedPlan().toString()
    got = {r.sample_id: sorted(v for v in r.x if v) for r in points.collect()}
    assert got == {"1": [1 / 5**0.5, 2 / 5**0.5], "4": [1.0], None: [1.0]} and all(len(r.x) == 128 for r in points.collect())
