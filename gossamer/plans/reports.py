"""Reports on runs: assignments met with their tables, traces by round, and their SQL."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gossamer.config import DescentConfig
from gossamer.functions import arrays as A
from gossamer.operators import descent, draws, metrics
from gossamer.plans import oracle
from gossamer.sources import points as S

CFG = DescentConfig()
L4 = oracle.POINTS["line4"]
CENTRES = CFG.with_(k=12)
METHODS = {"gossip": CFG, "silent": CFG.with_(comm="silent"), "no_window": CFG.with_(window=False)}


# --- traces ----------------------------------------------------------------------------------------------


def trace_of(points: DataFrame, cfg: DescentConfig, run_id: str) -> DataFrame:
    """``run_id, round, touched, error``: the first worker's mean error after each round; errors are over all points."""
    spark = points.sparkSession
    rows = descent.traced(draws.minibatches(points, cfg), cfg, descent.initial_state(points, cfg)).where("worker = 0").orderBy("round").select("round", "w").collect()  # a state a round
    states = spark.createDataFrame([(run_id, r["round"], r["round"] * cfg.b * cfg.workers, r.w) for r in rows], "run_id string, round int, touched long, w array<array<double>>")
    each = points.join(F.broadcast(states), F.lit(True))
    return each.groupBy("run_id", "round", "touched").agg(F.round(F.avg(F.array_min(A.distances("x", F.col("w"))) * 0.5) + 1.7e-11, 9).alias("error"))


def traces(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = S.line4(spark, sf_dir)
    return reduce(DataFrame.unionByName, [trace_of(points, cfg, name) for name, cfg in METHODS.items()])


def traces_sql() -> str:
    return " UNION ALL ".join(f"(SELECT * FROM ({oracle.trace(L4, cfg, 4, name)}) t)" for name, cfg in METHODS.items())


def trace_rollup(spark, sf_dir):
    return traces(spark, sf_dir).rollup("run_id", "touched").agg(F.count("*").alias("n"), F.min("error").alias("least")).fillna(-1, ["touched"])


def trace_progress(spark, sf_dir):
    """Running least error, improvement, and whether the last three rounds brought none."""
    own = Window.partitionBy("run_id").orderBy("round")
    t = traces(spark, sf_dir)
    best = F.min("error").over(own.rowsBetween(Window.unboundedPreceding, 0))
    before = F.min("error").over(own.rowsBetween(Window.unboundedPreceding, -3))
    return t.select("run_id", "round", best.alias("best"), F.round(F.lag("error").over(own) - F.col("error"), 9).alias("gain"), F.coalesce(best >= before, F.lit(False)).alias("stalled"))


def trace_pivot(spark, sf_dir):
    return traces(spark, sf_dir).groupBy("touched").pivot("run_id", list(METHODS)).agg(F.first("error"))


def trace_unpivot(spark, sf_dir):
    wide = trace_pivot(spark, sf_dir)
    return wide.unpivot(["touched"], list(METHODS), "run_id", "error")


def time_to_error(spark, sf_dir):
    """Samples until each method first reaches the error that the silent run ends with, and the ratio to it."""
    t = traces(spark, sf_dir)
    level = metrics.final_error(t).where("run_id = 'silent'").select(F.col("error").alias("level"))
    reached = t.join(F.broadcast(level), F.col("error") <= F.col("level")).groupBy("run_id").agg(F.min("touched").alias("touched"))
    base = reached.where("run_id = 'silent'").select(F.col("touched").alias("base"))
    return reached.join(F.broadcast(base), F.lit(True)).select("run_id", "touched", F.round(F.col("base") / F.col("touched"), 6).alias("fewer"))


# --- assignments ---------------------------------------------------------------------------------------------


def _clustered(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Line items with their cluster and distance by the first three prototypes."""
    points = S.line4(spark, sf_dir)
    state = spark.createDataFrame([(descent.initial_state(points, CFG),)], "w array<array<double>>")
    t = S.table(spark, sf_dir, "lineitem")
    x = F.array(F.col("l_quantity") / 50.0, F.col("l_extendedprice") / 105000.0, F.col("l_discount") * 10.0, F.col("l_tax") * 12.5)
    near = t.withColumn("x", x).join(F.broadcast(state), F.lit(True)).withColumn("ds", A.distances("x", F.col("w")))
    return near.withColumn("cluster", A.nearest("ds")).withColumn("d2", F.array_min("ds")).drop("w", "ds", "x")


def _clustered_sql(more: str) -> str:
    x = "[l_quantity / 50.0::double, l_extendedprice / 105000.0::double, l_discount * 10.0::double, l_tax * 12.5::double]"
    return f"(SELECT *, (list_position(ds, list_min(ds)) - 1)::int AS cluster, list_min(ds) AS d2 FROM (SELECT p.*, list_transform(z.w, lambda c: {oracle.d2('p.x', 'c', 4)}) AS ds FROM (SELECT *, {x} AS x FROM lineitem) p, ({oracle.initial(L4, CFG)}) z) n) {more}"


def cluster_cube(spark, sf_dir):
    rows = _clustered(spark, sf_dir).cube("l_returnflag", "l_linestatus", "cluster")
    return rows.agg(F.count("*").alias("n"), F.round(F.avg("d2") + 1.7e-11, 9).alias("mean_d2"), F.grouping_id().cast("long").alias("level")).fillna(-1, ["cluster"])


def cluster_regions(spark, sf_dir):
    """The mix of clusters by region: a star join with small sides broadcast by their size."""
    t = {n: S.table(spark, sf_dir, n) for n in ("orders", "customer", "nation", "region")}
    star = _clustered(spark, sf_dir).join(t["orders"], F.col("l_orderkey") == F.col("o_orderkey")).join(t["customer"], F.col("o_custkey") == F.col("c_custkey")).join(t["nation"], F.col("c_nationkey") == F.col("n_nationkey")).join(t["region"], F.col("n_regionkey") == F.col("r_regionkey"))
    return star.groupBy("r_name", "cluster").agg(F.count("*").alias("n"))


def majority_label(spark, sf_dir):
    """The cluster that most of three methods' results give a sample; of equal votes the lowest."""
    points = S.line4(spark, sf_dir)
    w0 = descent.initial_state(points, CFG)
    ends = [descent.gossip_sgd(points, cfg, w0) for cfg in METHODS.values()]
    votes = reduce(DataFrame.unionByName, [descent.assigned(points, descent.as_array(r.state()).tolist()) for r in ends])
    counted = votes.groupBy("sample_id", "cluster").agg(F.count("*").alias("votes"))
    return counted.groupBy("sample_id").agg(F.max_by("cluster", F.struct("votes", -F.col("cluster"))).alias("cluster")).groupBy("cluster").agg(F.count("*").alias("n"))


def majority_sql() -> str:
    one = lambda cfg: f"SELECT sample_id, (list_position(ds, list_min(ds)) - 1)::int AS cluster FROM (SELECT p.sample_id, list_transform(z.w, lambda c: {oracle.d2('p.x', 'c', 4)}) AS ds FROM ({L4}) p, (SELECT w FROM ({oracle.run(L4, cfg, 4, 'SELECT w FROM done WHERE worker = 0')}) y) z) n"
    votes = " UNION ALL ".join(one(c) for c in METHODS.values())
    return f"SELECT cluster, count(*) AS n FROM (SELECT sample_id, max((votes, -cluster))[2] * -1 AS cluster FROM (SELECT sample_id, cluster, count(*) AS votes FROM ({votes}) v GROUP BY ALL) c GROUP BY sample_id) m GROUP BY cluster"


def close_centres(spark, sf_dir):
    """Pairs of the line items' first prototypes nearer than a bound."""
    w = descent.initial_state(S.line4(spark, sf_dir), CENTRES)
    return S.close_centres(spark.createDataFrame(list(enumerate(w)), "center int, mu array<double>"), 0.5).select("a", "b", "distance")


def document_clusters(spark, sf_dir):
    """Share of good and toxic labels by the documents' nearest prototype."""
    points = S.doc128(spark, sf_dir)
    near = descent.assigned(points, descent.initial_state(points, CFG))
    labels = S.table(spark, sf_dir, "labels").withColumn("sample_id", F.col("doc_id").cast("string"))
    return near.join(labels, "sample_id").groupBy("cluster").agg(F.count("*").alias("n"), F.sum("quality").cast("long").alias("good"), F.sum("toxic").cast("long").alias("toxic"))


def codebook_sets(spark, sf_dir):
    """Codebook entries by language, by source and in all."""
    points = S.doc128(spark, sf_dir)
    near = descent.assigned(points, descent.initial_state(points, CFG))
    docs = S.table(spark, sf_dir, "documents").select(F.col("doc_id").cast("string").alias("sample_id"), "lang", "source")
    near.join(docs, "sample_id").createOrReplaceTempView("codebook_entries")
    return spark.sql("SELECT lang, source, cluster, count(*) AS n FROM codebook_entries GROUP BY GROUPING SETS ((lang, cluster), (source, cluster), (cluster))")


def _documents_sql() -> str:
    return f"(WITH pts AS MATERIALIZED ({oracle.documents()}) SELECT sample_id, (list_position(ds, list_min(ds)) - 1)::int AS cluster FROM (SELECT p.sample_id, list_transform(z.w, lambda c: {oracle.d2('p.x', 'c', 128)}) AS ds FROM pts p, ({oracle.initial('SELECT * FROM pts', CFG)}) z) n) near"


QUERIES = {f.__name__: f for f in (trace_rollup, trace_progress, trace_pivot, trace_unpivot, time_to_error, cluster_cube, cluster_regions, majority_label, close_centres, document_clusters, codebook_sets)} | {"trace_errors": traces}


def oracle_sql() -> dict[str, str]:
    t = traces_sql()
    pivot = f"SELECT touched, {', '.join(f'any_value(error) FILTER (run_id = {chr(39)}{m}{chr(39)}) AS {m}' for m in METHODS)} FROM ({t}) t GROUP BY touched"
    star = "JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"
    return {
        "trace_errors": t,
        "trace_rollup": f"SELECT run_id, coalesce(t.touched, -1)::bigint AS touched, count(*) AS n, min(error) AS least FROM ({t}) t GROUP BY ROLLUP (run_id, t.touched)",
        "trace_progress": f"SELECT run_id, round, min(error) OVER (o ROWS UNBOUNDED PRECEDING) AS best, round(lag(error) OVER o - error, 9) AS gain, coalesce(min(error) OVER (o ROWS UNBOUNDED PRECEDING) >= min(error) OVER (o ROWS BETWEEN UNBOUNDED PRECEDING AND 3 PRECEDING), false) AS stalled FROM ({t}) t WINDOW o AS (PARTITION BY run_id ORDER BY round)",
        "trace_pivot": pivot,
        "trace_unpivot": f"SELECT touched, run_id, error FROM ({t}) t",
        "time_to_error": f"WITH t AS MATERIALIZED ({t}), r AS (SELECT run_id, min(touched) AS touched FROM t WHERE error <= (SELECT max_by(error, round) FROM t WHERE run_id = 'silent') GROUP BY run_id) SELECT run_id, touched, round((SELECT touched FROM r WHERE run_id = 'silent') / touched::double, 6) AS fewer FROM r",
        "cluster_cube": f"SELECT l_returnflag, l_linestatus, coalesce(c.cluster, -1)::int AS cluster, count(*) AS n, round(avg(d2) + 1.7e-11, 9) AS mean_d2, grouping(l_returnflag, l_linestatus, c.cluster)::bigint AS level FROM {_clustered_sql('c')} GROUP BY CUBE (l_returnflag, l_linestatus, c.cluster)",
        "cluster_regions": f"SELECT r_name, cluster, count(*) AS n FROM {_clustered_sql('c')} {star} GROUP BY ALL",
        "majority_label": majority_sql(),
        "close_centres": f"SELECT a, b, distance FROM (SELECT p.i::int - 1 AS a, q.i::int - 1 AS b, sqrt({oracle.d2('w[p.i]', 'w[q.i]', 4)}) AS distance FROM ({oracle.initial(L4, CENTRES)}) z, range(1, 13) p(i), range(1, 13) q(i) WHERE p.i < q.i) d WHERE distance < 0.5",
        "document_clusters": f"SELECT cluster, count(*) AS n, sum(quality)::bigint AS good, sum(toxic)::bigint AS toxic FROM {_documents_sql()} JOIN labels l ON l.doc_id::varchar = sample_id GROUP BY cluster",
        "codebook_sets": f"SELECT lang, source, cluster, count(*) AS n FROM {_documents_sql()} JOIN documents d ON d.doc_id::varchar = sample_id GROUP BY GROUPING SETS ((lang, cluster), (source, cluster), (cluster))",
    }
