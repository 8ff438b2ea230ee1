"""Cost and accuracy measures, computed from given tables or from published numbers as relations."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import cost
from ..plans import evaluate, tasks
from ..plans.bandit import eliminate
from ..sources.tables import table
from .registry import entry, r6

Spark = SparkSession

#: Published models per hour by batch size and number of features.
THROUGHPUT = [
    (1, 100, 826.44), (1, 1000, 599.60), (1, 10000, 553.59),
    (2, 100, 1521.23), (2, 1000, 1214.37), (2, 10000, 701.07),
    (5, 100, 2411.53), (5, 1000, 3037.97), (5, 10000, 992.01),
    (8, 100, 5557.69), (8, 1000, 3502.79), (8, 10000, 1243.79),
    (10, 100, 7148.53), (10, 1000, 4216.44), (10, 10000, 1769.12),
    (15, 100, 7874.01), (15, 1000, 6260.14), (15, 10000, 2485.15),
    (20, 100, 11881.18), (20, 1000, 8248.36), (20, 10000, 2445.98),
]
#: A small history for curves and elimination; NaN marks a diverged model.
HISTORY = [
    ("a", 1, 10, "running", 0.60, 5.0), ("a", 2, 10, "running", 0.91, 7.0), ("a", 3, 10, "diverged", float("nan"), 8.0),
    ("a", 4, 100, "finished", 0.90, 20.0), ("a", 5, 10, "pruned", 0.55, 22.0), ("a", 6, 100, "finished", 0.94, 31.0),
    ("b", 1, 10, "running", 0.70, 4.0), ("b", 2, 100, "finished", 0.80, 9.0), ("b", 3, 100, "finished", 0.79, 15.0), ("b", 4, 20, "running", 0.80, 21.0),
]


def _values(rows: list[tuple], names: str) -> str:
    text = lambda v: repr(v) if not isinstance(v, float) or v == v else "'NaN'::DOUBLE"
    return f"(VALUES {', '.join('(' + ', '.join(text(v) for v in r) + ')' for r in rows)}) AS t({names})"


#: Orders by status and priority as levels and searches of an ablation: whole hundredths, so sums are exact.
_ORDERED = "(SELECT o_orderstatus AS level, o_orderpriority AS search, CAST(round(o_totalprice * 100) AS BIGINT) AS cost FROM orders) AS t"
#: Users' events as a history: a user is a run and an event a model; errors have diverged.
_RUNS = "(SELECT user_id AS run_id, event_id AS model_id, 1 + CAST(json_extract(props, '$.k') AS BIGINT) AS iters_done, CASE WHEN event_type = 'error' THEN 'NaN'::DOUBLE ELSE 100 / (110 + value) END AS quality, ts AS seconds FROM events) AS t"
_HISTORY = _values(HISTORY, "run_id, model_id, iters_done, status, quality, seconds")


def ordered(spark: Spark, d: str) -> DataFrame:
    return table(spark, d, "orders").select(F.col("o_orderstatus").alias("level"), F.col("o_orderpriority").alias("search"), F.round(F.col("o_totalprice") * 100).cast("long").alias("cost"))


def runs(spark: Spark, d: str) -> DataFrame:
    quality = F.when(F.col("event_type") == "error", float("nan")).otherwise(100 / (110 + F.col("value")))
    e = table(spark, d, "events").select(F.col("user_id").alias("run_id"), F.col("event_id").alias("model_id"), (1 + F.from_json("props", "k bigint")["k"]).alias("iters_done"), quality.alias("quality"), F.col("ts").alias("seconds"))
    return e.withColumn("valid_error", 1 - F.col("quality"))


def history(spark: Spark) -> DataFrame:
    return spark.createDataFrame(HISTORY, "run_id string, model_id int, iters_done int, status string, quality double, seconds double").withColumn("valid_error", 1 - F.col("quality"))


@entry("batching_speedup", "WITH t AS (SELECT l_linenumber AS batch, l_suppkey AS d, sum(l_quantity) / count(*) AS rate FROM lineitem GROUP BY 1, 2) SELECT a.batch, a.d, floor(a.rate / b.rate * 100) / 100 AS speedup FROM t a JOIN t b ON a.d = b.d AND b.batch = 1")
def batching_speedup(spark: Spark, d: str) -> DataFrame:
    """Quantity a line of every line number over that of the first one, for each supplier: truncated ratios."""
    lines = table(spark, d, "lineitem").groupBy(F.col("l_linenumber").alias("batch"), F.col("l_suppkey").alias("d"))
    t = lines.agg((F.sum("l_quantity") / F.count(F.lit(1))).alias("rate"))
    one = t.filter("batch = 1").select("d", F.col("rate").alias("one"))
    return t.join(one, "d").select("batch", "d", (F.floor(F.col("rate") / F.col("one") * 100) / 100).alias("speedup"))


@entry("ablation_speedup", f"WITH t AS (SELECT level, search, avg(cost) AS cost FROM {_ORDERED} GROUP BY level, search) SELECT a.level, a.search, round(b.cost / a.cost, 6) AS speedup, round(g.cost / a.cost, 6) AS against_urgent FROM t a JOIN t b ON a.search = b.search AND b.level = 'F' JOIN t g ON g.level = 'F' AND g.search = '1-URGENT'")
def ablation_speedup(spark: Spark, d: str) -> DataFrame:
    """Mean cost of finished orders over that of every status, at equal priority and at the first priority."""
    t = ordered(spark, d).groupBy("level", "search").agg(F.avg("cost").alias("cost"))
    base = t.filter("level = 'F'").select("search", F.col("cost").alias("base"))
    first = t.filter("level = 'F' and search = '1-URGENT'").select(F.col("cost").alias("first"))
    return t.join(base, "search").crossJoin(first).select("level", "search", r6(F.col("base") / F.col("cost")).alias("speedup"), r6(F.col("first") / F.col("cost")).alias("against_urgent"))


_PRIORITIES = {"1-URGENT": "urgent", "2-HIGH": "high", "3-MEDIUM": "medium", "4-NOT SPECIFIED": "unspecified", "5-LOW": "low"}


@entry("ablation_pivot", f"SELECT level, {', '.join(f"max(CASE WHEN search = '{k}' THEN cost END) AS {v}" for k, v in _PRIORITIES.items())} FROM {_ORDERED} GROUP BY level")
def ablation_pivot(spark: Spark, d: str) -> DataFrame:
    out = ordered(spark, d).groupBy("level").pivot("search", list(_PRIORITIES)).agg(F.max("cost"))
    return out.withColumnsRenamed(_PRIORITIES)


@entry("ablation_cube", f"SELECT level, search, round(avg(cost) / 100, 6) AS mean_cost FROM {_ORDERED} GROUP BY CUBE (level, search)")
def ablation_cube(spark: Spark, d: str) -> DataFrame:
    return ordered(spark, d).cube("level", "search").agg(r6(F.avg("cost") / 100).alias("mean_cost"))


@entry("end_to_end_gain", "WITH t AS (SELECT o_orderpriority AS search, avg(CAST(round(o_totalprice * 100) AS BIGINT)) AS cost, avg(CASE WHEN o_orderstatus = 'F' THEN 0.0 ELSE 1.0 END) AS test_error FROM orders GROUP BY 1) SELECT a.search, round(g.cost / a.cost, 6) AS sooner, round(a.test_error / nullif(g.test_error, 0) - 1, 6) AS relative_error FROM t a JOIN t g ON g.search = '1-URGENT'")
def end_to_end_gain(spark: Spark, d: str) -> DataFrame:
    """Mean cost and share of unfinished orders of every priority against the first one's."""
    unfinished = F.when(F.col("level") == "F", 0.0).otherwise(1.0)
    t = ordered(spark, d).groupBy("search").agg(F.avg("cost").alias("cost"), F.avg(unfinished).alias("test_error"))
    g = t.filter("search = '1-URGENT'").select(F.col("cost").alias("gc"), F.col("test_error").alias("ge"))
    return t.crossJoin(g).select("search", r6(F.col("gc") / F.col("cost")).alias("sooner"), r6(F.col("test_error") / F.nullif(F.col("ge"), F.lit(0.0)) - 1).alias("relative_error"))


@entry("roofline", "SELECT k, s, round(4.0 * k / (8.0 * s), 6) AS intensity, round(least(110.0, 60.0 * 4.0 * k / (8.0 * s)), 6) AS gflops FROM (VALUES (1), (2), (5), (8), (10), (15), (20)) a(k), (VALUES (1), (2)) b(s)")
def roofline(spark: Spark, d: str) -> DataFrame:
    m = cost.Machine()
    rows = [(k, s, round(cost.intensity(k, s), 6), round(cost.roofline(k, s, m), 6)) for k in (1, 2, 5, 8, 10, 15, 20) for s in (1, 2)]
    return spark.createDataFrame(rows, "k int, s int, intensity double, gflops double")


@entry("machine_balance", "SELECT round(110 / (60 / 8.0), 6) AS node, round(6.8 / 0.45, 6) AS core, round(110 / (60 * 0.5), 6) AS batch_one_scan, round(110 / (60 * 0.25), 6) AS batch_two_scans")
def machine_balance(spark: Spark, d: str) -> DataFrame:
    m = cost.Machine()
    row = (round(cost.balance(110, 60), 6), round(6.8 / 0.45, 6), round(cost.balance_batch(m, 1), 6), round(cost.balance_batch(m, 2), 6))
    return spark.createDataFrame([row], "node double, core double, batch_one_scan double, batch_two_scans double")


@entry("scheduling_overhead", "SELECT k, round(200.0 / k, 6) AS ms FROM (VALUES (1), (2), (5), (8), (10), (15), (20)) t(k)")
def scheduling_overhead(spark: Spark, d: str) -> DataFrame:
    return spark.createDataFrame([(k, round(cost.overhead_ms(200.0, k), 6)) for k in (1, 2, 5, 8, 10, 15, 20)], "k int, ms double")


_SIZED = [tasks.LINE_LINEAR, tasks.DOC_QUALITY, tasks.EMB_PLANE, tasks.CONTROL_EVENT, tasks.CONTROL_ORDER]


def _bytes_sql(task: tasks.Task) -> str:
    size = f"count(*)::DOUBLE * {len(task.features)} * 8"
    return f"SELECT '{task.name}' AS name, split, {size} AS bytes, round({size} / 1099511627776.0, 9) AS tib FROM ({tasks.task_sql(task)}) GROUP BY split"


@entry("data_bytes", " UNION ALL ".join(_bytes_sql(t) for t in _SIZED))
def data_bytes(spark: Spark, d: str) -> DataFrame:
    """Bytes of the feature matrix of every split of some tasks."""
    out = None
    for task in _SIZED:
        n = tasks.load(spark, d, task).groupBy("split").agg(F.count(F.lit(1)).cast("double").alias("n"))
        size = cost.data_bytes(F.col("n"), len(task.features))
        one = n.select(F.lit(task.name).alias("name"), "split", size.alias("bytes"), F.round(size / 2**40, 9).alias("tib"))
        out = one if out is None else out.unionByName(one)
    return out


@entry("work_and_traffic", "SELECT k, 4.0 * 600000 * 100 * k AS flops, 8.0 * 100 * k * 16 AS traffic, 4.0 * 600000 * 100 * k / (8.0 * 100 * k * 16) AS ratio FROM (VALUES (1), (10), (20)) t(k)")
def work_and_traffic(spark: Spark, d: str) -> DataFrame:
    rows = [(k, cost.flops(600_000, 100, k), cost.network_bytes(100, k, 16), cost.flops(600_000, 100, k) / cost.network_bytes(100, k, 16)) for k in (1, 10, 20)]
    return spark.createDataFrame(rows, "k int, flops double, traffic double, ratio double")


@entry("plan_cost_estimate", "SELECT name, models * (p + s * (t - p)) AS model_scans, models * (p + s * (t - p)) / k AS scans FROM (VALUES ('sequential', 100.0, 100.0, 1.0, 100.0, 1.0), ('bandit', 100.0, 10.0, 0.1, 100.0, 1.0), ('batching', 100.0, 100.0, 1.0, 100.0, 10.0), ('all', 100.0, 10.0, 0.1, 100.0, 10.0)) v(name, models, p, s, t, k)")
def plan_cost_estimate(spark: Spark, d: str) -> DataFrame:
    rows = []
    for name, partial, keep, k in (("sequential", 100, 1.0, 1), ("bandit", 10, 0.1, 1), ("batching", 100, 1.0, 10), ("all", 10, 0.1, 10)):
        e = cost.estimate(100, 100, 1.0, k, keep, partial)
        rows.append((name, e["model_scans"], e["scans"]))
    return spark.createDataFrame(rows, "name string, model_scans double, scans double")


@entry("scans_saved", "SELECT share, round(share * 0.9, 6) AS saved FROM (VALUES (0.0), (0.5), (0.92), (0.96), (1.0)) t(share)")
def scans_saved(spark: Spark, d: str) -> DataFrame:
    return spark.createDataFrame([(s, round(cost.saved_share(s, 10, 100), 6)) for s in (0.0, 0.5, 0.92, 0.96, 1.0)], "share double, saved double")


@entry("money", "SELECT nodes, hours, round(nodes * hours * 1.68, 2) AS dollars FROM (VALUES (128, 1.5), (128, 8.0), (16, 2.0)) t(nodes, hours)")
def money(spark: Spark, d: str) -> DataFrame:
    return spark.createDataFrame([(n, h, round(cost.dollars(n, h, 1.68), 2)) for n, h in ((128, 1.5), (128, 8.0), (16, 2.0))], "nodes int, hours double, dollars double")


@entry("best_so_far", f"SELECT run_id, model_id, round(min(CASE WHEN isnan(quality) THEN NULL ELSE 1 - quality END) OVER (PARTITION BY run_id ORDER BY seconds, model_id ROWS UNBOUNDED PRECEDING), 6) AS best_error FROM {_RUNS}")
def best_so_far(spark: Spark, d: str) -> DataFrame:
    return evaluate.curve(runs(spark, d)).select("run_id", "model_id", r6("best_error").alias("best_error"))


@entry("time_to_target", f"WITH h AS (SELECT *, CASE WHEN isnan(quality) THEN NULL ELSE 1 - quality END AS e FROM {_HISTORY}), c AS (SELECT *, min(e) OVER (PARTITION BY run_id ORDER BY seconds, model_id ROWS UNBOUNDED PRECEDING) AS b, min(e) OVER (PARTITION BY run_id) AS f FROM h) SELECT run_id, min(seconds) AS reached, round(min(f), 6) AS final_error FROM c WHERE b <= 1.8 * f GROUP BY run_id")
def time_to_target(spark: Spark, d: str) -> DataFrame:
    return evaluate.time_to(history(spark), 0.8).select("run_id", "reached", r6("final_error").alias("final_error"))


@entry("best_model", f"SELECT run_id, model_id, quality FROM (SELECT *, row_number() OVER (PARTITION BY run_id ORDER BY quality DESC, model_id) AS place FROM {_RUNS} WHERE NOT isnan(quality)) WHERE place = 1")
def best_model(spark: Spark, d: str) -> DataFrame:
    h = runs(spark, d).filter(F.col("quality").isNotNull() & ~F.isnan("quality"))
    return h.groupBy("run_id").agg(F.max_by("model_id", F.struct("quality", -F.col("model_id"))).alias("model_id"), F.max("quality").alias("quality"))


@entry("top_models", f"SELECT run_id, model_id, quality FROM {_HISTORY} WHERE NOT isnan(quality) ORDER BY quality DESC, run_id, model_id LIMIT 3")
def top_models(spark: Spark, d: str) -> DataFrame:
    return history(spark).filter(~F.isnan("quality")).select("run_id", "model_id", "quality").orderBy(F.desc("quality"), "run_id", "model_id").limit(3)


@entry("history_cube", f"SELECT run_id, status, count(*) AS n, sum(iters_done) AS iterations FROM {_HISTORY} GROUP BY CUBE (run_id, status)")
def history_cube(spark: Spark, d: str) -> DataFrame:
    return history(spark).cube("run_id", "status").agg(F.count(F.lit(1)).alias("n"), F.sum("iters_done").alias("iterations"))


def _verdict_sql(rule: str) -> str:
    """All events as the models of one run."""
    fits = "quality * 1.5 > best" if rule == "quality" else "(1 - quality) <= 1.5 * (1 - best)"
    return f"WITH h AS (SELECT * FROM {_RUNS}), b AS (SELECT max(quality) AS best FROM h WHERE NOT isnan(quality)) SELECT model_id, CASE WHEN isnan(quality) THEN 'dropped' WHEN iters_done >= 100 THEN 'finished' WHEN best IS NULL OR {fits} THEN 'active' ELSE 'dropped' END AS verdict FROM h, b"


@entry("eliminate_quality", _verdict_sql("quality"))
def eliminate_quality(spark: Spark, d: str) -> DataFrame:
    h = runs(spark, d)
    return eliminate(h, h, rule="quality").select("model_id", "verdict")


@entry("eliminate_error", _verdict_sql("error"))
def eliminate_error(spark: Spark, d: str) -> DataFrame:
    h = runs(spark, d)
    return eliminate(h, h, rule="error").select("model_id", "verdict")


_SLACKS = (0.0, 0.1, 0.5, 1.0, 1e9)


@entry("slack_sweep", "SELECT slack, count(*) FILTER (WHERE quality * (1 + slack) > best) AS kept FROM (SELECT * FROM " + _HISTORY + ") h, (SELECT max(quality) AS best FROM (SELECT * FROM " + _HISTORY + ") WHERE NOT isnan(quality)) b, (VALUES (0.0), (0.1), (0.5), (1.0), (1e9)) s(slack) WHERE NOT isnan(quality) GROUP BY slack")
def slack_sweep(spark: Spark, d: str) -> DataFrame:
    h = history(spark)
    out = None
    for s in _SLACKS:
        one = eliminate(h, h, slack=s, max_iterations=10**9).agg(F.count_if(F.col("verdict") == "active").alias("kept")).select(F.lit(s).alias("slack"), "kept")
        out = one if out is None else out.unionByName(one)
    return out


_P = [(1, 0.001), (2, 0.012), (3, 0.013), (4, 0.2), (5, 0.031), (6, 0.6)]


@entry("false_discovery", f"WITH r AS (SELECT model_id, p, row_number() OVER (ORDER BY p, model_id) AS rank, count(*) OVER () AS m FROM {_values(_P, 'model_id, p')}), c AS (SELECT coalesce(max(rank), 0) AS cut FROM r WHERE p <= 0.05 * rank / m) SELECT model_id, p, rank, rank <= cut AS rejected FROM r, c")
def false_discovery(spark: Spark, d: str) -> DataFrame:
    return evaluate.false_discovery_table(spark.createDataFrame(_P, "model_id int, p double"))


@entry("convergence_gain", f"WITH h AS (SELECT run_id, seconds, model_id, CASE WHEN isnan(quality) THEN NULL ELSE 1 - quality END AS e FROM {_RUNS}), c AS (SELECT *, min(e) OVER (PARTITION BY run_id ORDER BY model_id ROWS UNBOUNDED PRECEDING) AS b FROM h) SELECT run_id, model_id, round(b - lag(b) OVER (PARTITION BY run_id ORDER BY model_id), 6) AS change FROM c")
def convergence_gain(spark: Spark, d: str) -> DataFrame:
    c = evaluate.curve(runs(spark, d), by="model_id")
    return c.select("run_id", "model_id", r6(F.col("best_error") - F.lag("best_error").over(Window.partitionBy("run_id").orderBy("model_id"))).alias("change"))
