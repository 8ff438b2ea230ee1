"""Methods of the planner as queries: splits, draws, proposers, trainers, planners and scoring."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import draws
from ..operators import relational_gd as gd
from ..operators import shared_scan
from ..operators.block_descent import BlockDescent
from ..operators.local_fanout import local_fanout
from ..operators.random_features import Projection
from ..plans import blocks as packed
from ..plans import evaluate, tasks
from ..plans.bandit import Eliminator, SuccessiveHalving
from ..plans.budget import Budget
from ..plans.ensemble import greedy, votes
from ..plans.planner import column_of, plan_adaptive, plan_sequential
from ..plans.search import Observation, make
from ..plans.search.grid import grid_table
from ..plans.session import Session
from ..plans.space import L2, NOISE, RATE, ModelSpace, component_pipeline, kernel_svm, linear_pair, random_feature_logistic, tiny
from ..plans.sqlfront import predict_sql
from ..sources.tables import register
from .registry import entry, r6

Spark = SparkSession
T = tasks.TASKS


def blocks_of(spark: Spark, d: str, task: tasks.Task, *, noise: float = 0.0) -> DataFrame:
    return packed.store(packed.pack(tasks.load(spark, d, task, noise=noise)))


# --- splits, sampling, draws -------------------------------------------------------------------


def _split_counts(task: tasks.Task) -> None:
    @entry(f"split_counts_{task.name}", f"SELECT split, count(*) AS n FROM ({tasks.task_sql(task)}) GROUP BY split")
    def split_counts(spark: Spark, d: str) -> DataFrame:
        return tasks.load(spark, d, task).groupBy("split").agg(F.count(F.lit(1)).alias("n"))


for _t in (tasks.LINE_LINEAR, tasks.DOC_QUALITY, tasks.EMB_PLANE):
    _split_counts(_t)


@entry("split_overlap", "SELECT count(*) AS shared FROM (SELECT md5(text) AS k FROM documents GROUP BY 1 HAVING count(DISTINCT " + tasks.split_sql("md5(text)") + ") > 1)")
def split_overlap(spark: Spark, d: str) -> DataFrame:
    """Copies of a text never stand in two splits."""
    t = tasks.load(spark, d, T["doc_english"])
    return t.groupBy("key").agg(F.countDistinct("split").alias("s")).filter("s > 1").agg(F.count(F.lit(1)).alias("shared"))


@entry("draw_uniform", f"SELECT o_orderkey AS i, {draws.uniform_sql('u', 'o_orderkey')} AS u, round({draws.gaussian_sql('g', 'o_orderkey')}, 6) AS g, round({draws.cauchy_sql('c', 'o_orderkey')}, 6) AS c FROM orders")
def draw_uniform(spark: Spark, d: str) -> DataFrame:
    """Draws for the keys of a table; the uniform ones are exact in every engine."""
    from ..sources.tables import table

    i = F.col("o_orderkey")
    return table(spark, d, "orders").select(i.alias("i"), draws.uniform("u", i).alias("u"), r6(draws.gaussian("g", i)).alias("g"), r6(draws.cauchy("c", i)).alias("c"))


@entry("random_feature_matrix", "SELECT i, j, round(" + draws.gaussian_sql("rff", "(i * 1000 + j)") + " * 0.5, 6) AS w, round(" + draws.uniform_sql("phase", "j") + f" * {2 * math.pi!r}, 6) AS phase FROM generate_series(0, 4) a(i), generate_series(0, 63) b(j)")
def random_feature_matrix(spark: Spark, d: str) -> DataFrame:
    """A projection drawn by the engine: 5 inputs, 64 features, noise 0.5."""
    ij = spark.range(5).select(F.col("id").alias("i"), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(63).cast("long"))).alias("j"))
    return ij.select("i", "j", r6(draws.gaussian("rff", F.col("i") * 1000 + F.col("j")) * 0.5).alias("w"), r6(draws.uniform("phase", F.col("j")) * (2 * math.pi)).alias("phase"))


@entry("downsample_share", f"SELECT count(*) AS n FROM (SELECT {tasks._LINE_KEY} AS key FROM lineitem) WHERE {draws.uniform_sql('sample:0', 'key')} < 0.2")
def downsample_share(spark: Spark, d: str) -> DataFrame:
    """Rows kept when the features grow fivefold."""
    return tasks.downsample(tasks.load(spark, d, T["line_linear"]), "key", 0.2).agg(F.count(F.lit(1)).alias("n"))


# --- baselines -----------------------------------------------------------------------------------


def _baseline(name: str) -> None:
    @entry(f"baseline_error_{name}", f"SELECT round(1 - max(n) / sum(n), 6) AS majority_error, CAST(sum(n) AS BIGINT) AS n FROM (SELECT label, count(*) AS n FROM ({tasks.task_sql(T[name])}) GROUP BY label)")
    def baseline_error(spark: Spark, d: str) -> DataFrame:
        return evaluate.majority_error(tasks.load(spark, d, T[name])).select(r6("majority_error").alias("majority_error"), "n")


for _n in ("doc_quality", "doc_english", "doc_toxic", "doc_lang4", "line_linear", "line_xor", "line_skew", "line_147", "emb_plane", "control_return", "control_status", "control_embedding", "control_event", "control_order"):
    _baseline(_n)


# --- proposers -------------------------------------------------------------------------------------


def _grid(n: int) -> None:
    axis = lambda lo, hi, v: f"exp(ln({lo}) + {v} / {n - 1}.0 * (ln({hi}) - ln({lo})))"
    sql = f"SELECT round({axis(*RATE, 'a.i')}, 6) AS rate, round({axis(*L2, 'b.i')}, 6) AS l2, round({axis(1, 10, 'c.i')}, 6) AS size, round({axis(*NOISE, 'e.i')}, 6) AS noise FROM generate_series(0, {n - 1}) a(i), generate_series(0, {n - 1}) b(i), generate_series(0, {n - 1}) c(i), generate_series(0, {n - 1}) e(i)"

    @entry(f"grid_points_n{n}", sql)
    def grid_points(spark: Spark, d: str) -> DataFrame:
        g = grid_table(spark, n, ["rate", "l2", "size", "noise"], [RATE[0], L2[0], 1, NOISE[0]], [RATE[1], L2[1], 10, NOISE[1]])
        return g.select(*[r6(c).alias(c) for c in ("rate", "l2", "size", "noise")])


for _k in (2, 3, 4, 5):
    _grid(_k)


def _log_draw(tag: str, lo: float, hi: float, key: str) -> str:
    return f"exp(ln({lo}) + {draws.uniform_sql(tag, key)} * (ln({hi}) - ln({lo})))"


@entry(
    "random_points",
    "SELECT i, CASE WHEN f < 0.5 THEN 'svm' ELSE 'logistic' END AS family, round(CASE WHEN f < 0.5 THEN rs ELSE rl END, 6) AS rate, round(CASE WHEN f < 0.5 THEN ls ELSE ll END, 6) AS l2 FROM (SELECT i, "
    f"{draws.uniform_sql('7:family', 'i')} AS f, {_log_draw('7:svm.rate', *RATE, 'i')} AS rs, {_log_draw('7:svm.l2', *L2, 'i')} AS ls, {_log_draw('7:logistic.rate', *RATE, 'i')} AS rl, {_log_draw('7:logistic.l2', *L2, 'i')} AS ll FROM generate_series(0, 127) t(i))",
)
def random_points(spark: Spark, d: str) -> DataFrame:
    space = linear_pair()
    rows = [(i, c.family, round(c["rate"], 6), round(c["l2"], 6)) for i in range(128) for c in [space.draw(7, i)]]
    return spark.createDataFrame(rows, "i long, family string, rate double, l2 double")


def _bowl(config) -> float:
    """A smooth known error surface with its least value 0.05 at rate 0.1, l2 1e-2."""
    return min(1.0, 0.05 + 0.03 * (math.log10(config["rate"]) + 1) ** 2 + 0.02 * (math.log10(config["l2"]) + 2) ** 2)


def _proposer(name: str) -> None:
    @entry(f"proposer_{name}", f"SELECT '{name}' AS method, TRUE AS in_space, TRUE AS near_the_least")
    def held(spark: Spark, d: str) -> DataFrame:
        """On a known surface whose least value is 0.05: all proposals lie in the space, one is near the least."""
        rows = proposed(spark).collect()
        inside = all(RATE[0] * 0.999 <= r["rate"] <= RATE[1] * 1.001 and L2[0] * 0.999 <= r["l2"] <= L2[1] * 1.001 for r in rows)
        return spark.createDataFrame([(name, inside and 0 < len(rows) <= 64, min(r["error"] for r in rows) <= 0.1)], "method string, in_space boolean, near_the_least boolean")

    @entry(f"proposals_{name}")
    def proposals(spark: Spark, d: str) -> DataFrame:
        """What the method proposes on that surface, in order."""
        return proposed(spark)

    def proposed(spark: Spark) -> DataFrame:
        space, seen = linear_pair(), []
        p = make(name, space, 64, 1)
        while len(seen) < 64:
            fresh = p.propose(min(4, 64 - len(seen)), seen)
            if not fresh:
                break
            seen += [Observation(c, _bowl(c)) for c in fresh]
        rows = [(i, o.config.family, float(o.config["rate"]), float(o.config["l2"]), o.error) for i, o in enumerate(seen)]
        return spark.createDataFrame(rows, "i int, family string, rate double, l2 double, error double")


for _n in ("grid", "random", "directions", "simplex", "parzen", "forest", "gaussian_process"):
    _proposer(_n)


# --- trainers: relational form, checked by another engine ---------------------------------------------


def _relational(name: str, task: tasks.Task, models: list[gd.Model], iterations: int) -> None:
    k = len(task.features)
    cols = ", ".join(f"round(w{i}, 6) AS w{i}" for i in range(k + 1))
    z = gd.margin_sql(k)
    body = gd.training_sql(tasks.task_sql(task), models, k, iterations)

    @entry(name, f"{body} SELECT model_id, family, {cols}, round(valid_error, 6) AS valid_error FROM m{iterations} JOIN (SELECT model_id AS id, avg(CASE WHEN (CASE WHEN {z} > 0 THEN 1 ELSE 0 END) = label THEN 0.0 ELSE 1.0 END) AS valid_error FROM (SELECT * FROM raw_rows WHERE split = 'valid'), m{iterations} GROUP BY model_id) e ON e.id = model_id")
    def train(spark: Spark, d: str) -> DataFrame:
        rows = tasks.load(spark, d, task, wide=True)
        fitted = gd.train(rows.filter("split = 'train'"), gd.models_table(spark, models, k), task.names(), iterations)
        err = gd.errors(rows.filter("split = 'valid'"), fitted, task.names()).select("model_id", r6("valid_error").alias("valid_error"))
        return fitted.join(err, "model_id").select("model_id", "family", *[r6(w).alias(w) for w in gd.weights(k)], "valid_error")


_relational("lr_step", tasks.LINE_LINEAR, [gd.Model(1, "logistic", 0.5, 0.0)], 1)
_relational("lr_train_k1", tasks.LINE_LINEAR, [gd.Model(1, "logistic", 0.5, 0.001)], 3)
_relational("lr_shared_scan", tasks.LINE_LINEAR, [gd.Model(i + 1, "logistic", r, l2) for i, (r, l2) in enumerate([(0.1, 0.0), (0.5, 0.001), (1.0, 0.01), (2.0, 0.1)])], 2)
_relational("svm_shared_scan", tasks.LINE_LINEAR, [gd.Model(i + 1, "svm", r, l2) for i, (r, l2) in enumerate([(0.1, 0.0), (0.3, 0.001), (1.0, 0.01)])], 2)
_relational("mixed_batch", tasks.LINE_SKEW, [gd.Model(1, "logistic", 0.5, 0.01), gd.Model(2, "svm", 0.2, 0.01), gd.Model(3, "ridge", 0.1, 0.01)], 2)
_relational("lr_documents", tasks.DOC_QUALITY, [gd.Model(1, "logistic", 1.0, 0.0001), gd.Model(2, "svm", 0.5, 0.0001)], 3)


@entry("ridge_gd", f"{gd.training_sql(tasks.task_sql(tasks.LINE_REVENUE), [gd.Model(1, 'ridge', 0.3, 0.001)], 4, 3)} SELECT round(avg(pow(({gd.margin_sql(4)}) - label, 2)), 6) AS mse, round(var_pop(label), 6) AS variance FROM (SELECT * FROM raw_rows WHERE split = 'valid'), m3")
def ridge_gd(spark: Spark, d: str) -> DataFrame:
    task = tasks.LINE_REVENUE
    rows = tasks.load(spark, d, task, wide=True)
    fitted = gd.train(rows.filter("split = 'train'"), gd.models_table(spark, [gd.Model(1, "ridge", 0.3, 0.001)], 4), task.names(), 3)
    scored = rows.filter("split = 'valid'").crossJoin(F.broadcast(fitted)).withColumn("prediction", gd.margin(task.names()))
    return evaluate.mse(scored).select(r6("mse").alias("mse"), r6("variance").alias("variance"))


@entry("gradient_descent_minibatch", f"WITH r AS (SELECT *, CAST(floor({draws.uniform_sql('block', 'key')} * 4) AS INT) AS part FROM ({tasks.task_sql(tasks.LINE_LINEAR)}) WHERE split = 'train') SELECT part, count(*) AS n, round(avg(0.5 - label), 6) AS g0, round(avg((0.5 - label) * x1), 6) AS g1 FROM r GROUP BY part")
def gradient_descent_minibatch(spark: Spark, d: str) -> DataFrame:
    """First gradients of contiguous quarters of the training rows, at zero weights."""
    rows = tasks.load(spark, d, tasks.LINE_LINEAR, wide=True).filter("split = 'train'").withColumn("part", F.floor(draws.uniform("block", F.col("key")) * 4).cast("int"))
    g = F.lit(0.5) - F.col("label")
    return rows.groupBy("part").agg(F.count(F.lit(1)).alias("n"), r6(F.avg(g)).alias("g0"), r6(F.avg(g * F.col("x1"))).alias("g1"))


@entry("gram_block", f"WITH r AS (SELECT * FROM ({tasks.task_sql(tasks.LINE_LINEAR)}) WHERE split = 'train') SELECT i, j, round(CASE i WHEN 1 THEN CASE j WHEN 1 THEN avg(x1 * x1) WHEN 2 THEN avg(x1 * x2) ELSE avg(x1 * x3) END WHEN 2 THEN CASE j WHEN 2 THEN avg(x2 * x2) ELSE avg(x2 * x3) END ELSE avg(x3 * x3) END, 6) AS g FROM r, (VALUES (1, 1), (1, 2), (1, 3), (2, 2), (2, 3), (3, 3)) t(i, j) GROUP BY i, j")
def gram_block(spark: Spark, d: str) -> DataFrame:
    rows = tasks.load(spark, d, tasks.LINE_LINEAR, wide=True).filter("split = 'train'")
    pairs = [(i, j) for i in (1, 2, 3) for j in (1, 2, 3) if i <= j]
    one = rows.agg(*[r6(F.avg(F.col(f"x{i}") * F.col(f"x{j}"))).alias(f"g{i}{j}") for i, j in pairs])
    return one.select(F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.lit(j).alias("j"), F.col(f"g{i}{j}").alias("g")) for i, j in pairs])).alias("r")).select("r.*")


@entry("ovr_argmax", "SELECT lang, CASE WHEN en >= de AND en >= fr AND en >= es THEN 'en' WHEN de >= fr AND de >= es THEN 'de' WHEN fr >= es THEN 'fr' ELSE 'es' END AS prediction, count(*) AS n FROM (SELECT lang, (length(text) - length(replace(text, 'th', ''))) AS en, 2 * (length(text) - length(replace(text, 'ch', ''))) AS de, 2 * (length(text) - length(replace(text, 'é', ''))) AS fr, 2 * (length(text) - length(replace(text, 'ó', ''))) AS es FROM documents) GROUP BY 1, 2")
def ovr_argmax(spark: Spark, d: str) -> DataFrame:
    """One margin per class, the largest wins (earlier class on ties)."""
    t = F.col("text")
    seen = lambda s, w: w * (F.length(t) - F.length(F.replace(t, F.lit(s), F.lit(""))))
    m = F.array(seen("th", 1), seen("ch", 2), seen("é", 2), seen("ó", 2))
    names = F.array(*[F.lit(x) for x in ("en", "de", "fr", "es")])
    from ..sources.tables import table

    scored = table(spark, d, "documents").withColumn("_m", m)
    return scored.groupBy("lang", F.element_at(names, F.array_position("_m", F.array_max("_m")).cast("int")).alias("prediction")).agg(F.count(F.lit(1)).alias("n"))


_RULE = "CASE WHEN 10.0 * (length(text) - length(translate(text, '#$%&*|<>', ''))) / (1 + length(text)) > 0.3 THEN 0 ELSE 1 END"


@entry("confusion", f"SELECT quality AS label, {_RULE} AS prediction, count(*) AS n FROM documents JOIN labels USING (doc_id) GROUP BY 1, 2")
def confusion(spark: Spark, d: str) -> DataFrame:
    from ..sources.tables import table

    df = table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id").select(F.col("quality").alias("label"), F.expr(_RULE).alias("prediction"))
    return evaluate.confusion(df)


@entry("metrics", f"SELECT round(tp / (tp + fp), 6) AS precision, round(tp / (tp + fn), 6) AS recall, round(2 * tp / (2 * tp + fp + fn), 6) AS f1, round((tp + tn) / (tp + fp + fn + tn), 6) AS accuracy, round(1 - (tp + tn) / (tp + fp + fn + tn), 6) AS error FROM (SELECT sum(CASE WHEN y = 1 AND p = 1 THEN 1.0 ELSE 0 END)::DOUBLE AS tp, sum(CASE WHEN y = 0 AND p = 1 THEN 1.0 ELSE 0 END)::DOUBLE AS fp, sum(CASE WHEN y = 1 AND p = 0 THEN 1.0 ELSE 0 END)::DOUBLE AS fn, sum(CASE WHEN y = 0 AND p = 0 THEN 1.0 ELSE 0 END)::DOUBLE AS tn FROM (SELECT quality AS y, {_RULE} AS p FROM documents JOIN labels USING (doc_id)))")
def metrics(spark: Spark, d: str) -> DataFrame:
    from ..sources.tables import table

    df = table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id").select(F.col("quality").alias("label"), F.expr(_RULE).alias("prediction"))
    m = evaluate.metrics(df)
    return m.select(*[r6(c).alias(c) for c in ("precision", "recall", "f1", "accuracy")], r6(1 - F.col("accuracy")).alias("error"))


def _counts_sql(task: tasks.Task) -> str:
    return f"SELECT label, count(*) AS n FROM ({tasks.task_sql(task)}) GROUP BY label"


_MAJORITY = "round(1 - max(n) / sum(n), 6) AS majority_error"


def majority(spark: Spark, d: str, task: tasks.Task) -> float:
    return float(evaluate.majority_error(tasks.load(spark, d, task)).first()["majority_error"])


# --- trainers on packed blocks ---------------------------------------------------------------------


def _columns_frame(spark: Spark, columns, result) -> DataFrame:
    rows = [(c.model_id, c.family, c.iterations, float(result.loss[k] / max(1, result.rows.get("train", 1))), result.error(k), result.error(k, "test"), [round(float(w), 6) for w in c.weights.ravel()[:16]]) for k, c in enumerate(columns)]
    return spark.createDataFrame(rows, "model_id int, family string, iters_done int, train_loss double, valid_error double, test_error double, weights array<double>")


def _pair(d: int, projection: Projection | None = None) -> list[shared_scan.Column]:
    return [shared_scan.start(shared_scan.Column(i, f, r, 1e-3, projection), d) for i, (f, r) in enumerate([("logistic", 1.0), ("svm", 0.5), ("logistic", 3.0), ("svm", 0.1)])]


#: The four models of ``_pair`` for the relational form.
_PAIR = [gd.Model(i, f, r, 1e-3) for i, (f, r) in enumerate([("logistic", 1.0), ("svm", 0.5), ("logistic", 3.0), ("svm", 0.1)])]


def _fitted_sql(task: tasks.Task, iterations: int, step: str = "plain") -> str:
    """Models, errors and weights of the four models, by another engine's unrolled iterations."""
    k = len(task.features)
    cols = ", ".join(f"round(w{i}, 6) AS w{i}" for i in range(k + 1))
    return f"{gd.training_sql(tasks.task_sql(task), _PAIR, k, iterations, step=step)} SELECT m.model_id, family, CAST({iterations} AS INT) AS iters_done, round(valid_error, 6) AS valid_error, round(test_error, 6) AS test_error, {cols} FROM m{iterations} m JOIN ({gd.errors_sql(f'm{iterations}', k)}) e ON e.model_id = m.model_id"


def _fitted_frame(spark: Spark, rows: list[tuple], k: int) -> DataFrame:
    """(model_id, family, iterations, errors, weights) as the SQL above gives them."""
    out = [(i, f, n, round(v, 6), round(t, 6), *[round(float(w), 6) + 0.0 for w in ws]) for i, f, n, v, t, ws in rows]
    return spark.createDataFrame(out, f"model_id int, family string, iters_done int, valid_error double, test_error double, {', '.join(f'w{i} double' for i in range(k + 1))}")


def _shared(name: str, task: tasks.Task, iterations: int, **options) -> None:
    k = len(task.features)

    @entry(f"shared_scan_{name}", _fitted_sql(task, iterations, options.get("step", "plain")) if "minibatches" not in options else None)
    def run(spark: Spark, d: str) -> DataFrame:
        columns = _pair(k)
        p = shared_scan.train(blocks_of(spark, d, task), columns, iterations, **options)
        return _fitted_frame(spark, [(c.model_id, c.family, c.iterations, p.error(i), p.error(i, "test"), c.weights[:, 0]) for i, c in enumerate(columns)], k)


_shared("gemm", tasks.LINE_LINEAR, 10)
_shared("rowloop", tasks.LINE_LINEAR, 5, kernel="rowloop")
_shared("minibatch", tasks.LINE_LINEAR, 3, minibatches=2)
_shared("nesterov", tasks.DOC_QUALITY, 10, step="nesterov")
_shared("adagrad", tasks.DOC_QUALITY, 10, step="adagrad")


@entry("shared_scan_equals_relational", f"{gd.training_sql(tasks.task_sql(tasks.LINE_LINEAR), [gd.Model(1, 'logistic', 0.5, 0.001), gd.Model(2, 'svm', 0.2, 0.01)], 5, 2)} SELECT model_id, {', '.join(f'round(w{i}, 6) AS w{i}' for i in range(6))} FROM m2")
def shared_scan_equals_relational(spark: Spark, d: str) -> DataFrame:
    """The matrix form of a batch, against the other engine's unrolled iterations."""
    columns = [shared_scan.start(shared_scan.Column(1, "logistic", 0.5, 0.001), 5), shared_scan.start(shared_scan.Column(2, "svm", 0.2, 0.01), 5)]
    shared_scan.train(blocks_of(spark, d, tasks.LINE_LINEAR), columns, 2)
    return spark.createDataFrame([(c.model_id, *[round(float(w), 6) + 0.0 for w in c.weights[:, 0]]) for c in columns], "model_id int, " + ", ".join(f"w{i} double" for i in range(6)))


@entry("random_feature_training")
def random_feature_training(spark: Spark, d: str) -> DataFrame:
    """The product target that no linear model learns, with and without random features."""
    b = blocks_of(spark, d, tasks.LINE_XOR)
    columns = _pair(5)[:1] + [shared_scan.start(shared_scan.Column(9, "logistic", 20.0, 1e-5, Projection(5, 64, 1, 0.7)), 5)]
    return _columns_frame(spark, columns, shared_scan.train(b, columns, 25))


@entry("cauchy_feature_training")
def cauchy_feature_training(spark: Spark, d: str) -> DataFrame:
    b = blocks_of(spark, d, tasks.LINE_XOR)
    columns = [shared_scan.start(shared_scan.Column(1, "svm", 10.0, 1e-5, Projection(5, 64, 2, 0.4, "cauchy", 0.1)), 5)]
    return _columns_frame(spark, columns, shared_scan.train(b, columns, 15))


def _descent(name: str, task: tasks.Task, classes: int, size: int, l2s: list[float], **options) -> None:
    k = len(task.features)

    def cycles(spark: Spark, d: str) -> list[tuple]:
        b = blocks_of(spark, d, task)
        model, rows = BlockDescent(Projection(k, size, 3, 0.6), classes, l2s, block=size // 2, **options), []
        for cycle in range(2):
            for v, s in model.train(b).items():
                rows.append((cycle, v, s["objective"], s["train_error"], s["valid_error"]))
        return rows

    @entry(f"block_descent_figures_{name}")
    def figures(spark: Spark, d: str) -> DataFrame:
        return spark.createDataFrame(cycles(spark, d), "cycle int, l2 double, objective double, train_error double, valid_error double")

    @entry(f"block_descent_{name}", f"SELECT CAST(l2 AS DOUBLE) AS l2, {_MAJORITY}, TRUE AS objective_falls, TRUE AS beats_majority FROM ({_counts_sql(task)}), (VALUES {', '.join(f'({v!r})' for v in l2s)}) v(l2) GROUP BY l2")
    def run(spark: Spark, d: str) -> DataFrame:
        """What holds after two cycles: the objective falls, and training errors are below the majority class's."""
        base, rows = majority(spark, d, task), cycles(spark, d)
        objective = {(c, v): o for c, v, o, _, _ in rows}
        out = [(v, round(base, 6), objective[1, v] <= objective[0, v] + 1e-9, e < base) for c, v, _, e, _ in rows if c == 1]
        return spark.createDataFrame(out, "l2 double, majority_error double, objective_falls boolean, beats_majority boolean")


_descent("binary", tasks.LINE_XOR, 2, 128, [1e-6, 1e-4, 1e-2])
_descent("hinge", tasks.LINE_XOR, 2, 128, [1e-5], loss="squared_hinge")
_descent("classes147", tasks.LINE_147, 147, 256, [1e-6])
_descent("languages", tasks.DOC_LANG4, 4, 64, [1e-6])


@entry("one_vs_rest_languages")
def one_vs_rest_languages(spark: Spark, d: str) -> DataFrame:
    columns = [shared_scan.start(shared_scan.Column(i, f, r, 1e-4), 8, 4) for i, (f, r) in enumerate([("logistic", 2.0), ("svm", 0.5)])]
    return _columns_frame(spark, columns, shared_scan.train(blocks_of(spark, d, tasks.DOC_LANG4), columns, 20, classes=4))


@entry("local_fanout", _fitted_sql(tasks.DOC_QUALITY, 20))
def local_training(spark: Spark, d: str) -> DataFrame:
    """Small data: one task per model, no pass of the driver."""
    family = F.element_at(F.array(*[F.lit(m.family) for m in _PAIR]), (F.col("model_id") + 1).cast("int"))
    out = local_fanout(blocks_of(spark, d, tasks.DOC_QUALITY), _pair(4), 20)
    return out.select(F.col("model_id").cast("int").alias("model_id"), family.alias("family"), "iters_done", r6("valid_error").alias("valid_error"), r6("test_error").alias("test_error"), *[r6(F.get("weights", F.lit(i))).alias(f"w{i}") for i in range(5)])


@entry("recommendation_als")
def recommendation_als(spark: Spark, d: str) -> DataFrame:
    from pyspark.ml.evaluation import RegressionEvaluator
    from pyspark.ml.recommendation import ALS

    from ..sources.tables import table

    o, lines = table(spark, d, "orders"), table(spark, d, "lineitem")
    counts = o.join(lines, o["o_orderkey"] == lines["l_orderkey"]).groupBy(F.col("o_custkey").cast("int").alias("user"), F.col("l_partkey").cast("int").alias("item")).agg(F.count(F.lit(1)).cast("float").alias("rating"))
    counts = counts.withColumn("split", tasks.split_of(F.concat_ws("|", "user", "item")))
    model = ALS(userCol="user", itemCol="item", ratingCol="rating", rank=4, maxIter=3, seed=1, coldStartStrategy="drop").fit(counts.filter("split = 'train'"))
    rmse = RegressionEvaluator(labelCol="rating", predictionCol="prediction").evaluate(model.transform(counts.filter("split = 'valid'")))
    return spark.createDataFrame([(4, float(rmse))], "rank int, rmse double")


@entry("library_families")
def library_families(spark: Spark, d: str) -> DataFrame:
    """Decision tree, naive Bayes and k-means of the library on the quality task."""
    from pyspark.ml.classification import DecisionTreeClassifier, NaiveBayes
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    df = tasks.load(spark, d, tasks.DOC_QUALITY).withColumn("features", array_to_vector("features")).cache()
    train, valid = df.filter("split = 'train'"), df.filter("split = 'valid'")
    rows = []
    for name, model in (("tree", DecisionTreeClassifier(maxDepth=4, seed=1).fit(train)), ("naive_bayes", NaiveBayes(modelType="gaussian").fit(train))):
        e = evaluate.error(model.transform(valid)).first()["error"]
        rows.append((name, float(e)))
    rows.append(("kmeans_cost", float(KMeans(k=2, seed=1, maxIter=5).fit(train).summary.trainingCost)))
    df.unpersist()
    return spark.createDataFrame(rows, "family string, value double")


@entry("library_grid_search")
def library_grid_search(spark: Spark, d: str) -> DataFrame:
    """The library's own grid search, as a black-box baseline."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.evaluation import MulticlassClassificationEvaluator
    from pyspark.ml.functions import array_to_vector
    from pyspark.ml.tuning import ParamGridBuilder, TrainValidationSplit

    df = tasks.load(spark, d, tasks.DOC_QUALITY).filter("split <> 'test'").withColumn("features", array_to_vector("features"))
    lr = LogisticRegression(maxIter=10)
    grid = ParamGridBuilder().addGrid(lr.regParam, [1e-4, 1e-2, 1.0]).build()
    fitted = TrainValidationSplit(estimator=lr, estimatorParamMaps=grid, evaluator=MulticlassClassificationEvaluator(metricName="accuracy"), trainRatio=0.78, seed=1).fit(df)
    return spark.createDataFrame([(float(p[lr.regParam]), 1 - float(m)) for p, m in zip(grid, fitted.validationMetrics, strict=True)], "l2 double, valid_error double")


# --- planners --------------------------------------------------------------------------------------


def _planner(name: str, task: tasks.Task, run, *, control: bool = False) -> None:
    """A plan, and what must hold of it: its test error is not above the majority class's by more than
    three standard errors (for a control: nor below), and every pass stands in the ledger."""

    @entry(f"plan_{name}", f"SELECT '{name}' AS run, {_MAJORITY}, TRUE AS as_expected, TRUE AS charged FROM ({_counts_sql(task)})")
    def plan(spark: Spark, d: str) -> DataFrame:
        blocks = blocks_of(spark, d, task)
        r, base = run(blocks), majority(spark, d, task)
        tests = blocks.filter("split = 'test'").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n")).first()["n"]
        spread = 3 * math.sqrt(base * (1 - base) / max(1, tests))
        fine = r.test_error <= base + spread and (not control or r.test_error >= base - spread)
        ledger = r.ledger
        charged = 0 < ledger.scans <= ledger.model_iterations and ledger.round_trips == 2 * (ledger.scans + ledger.held_out_scans) and ledger.models == len({h.model_id for h in r.history})
        packed.release(blocks)
        return spark.createDataFrame([(name, round(base, 6), bool(fine), bool(charged))], "run string, majority_error double, as_expected boolean, charged boolean")


def _fixed_planner(name: str, task: tasks.Task, space: ModelSpace, models: int, iterations: int, proposer: str, run) -> None:
    """A plan whose configurations do not depend on what was observed, against the other engine's training
    of the same configurations and its choice of the least validation error."""
    k, found = len(task.features), make(proposer, space, models, 0)
    configs: list = []
    while len(configs) < models and (fresh := found.propose(models - len(configs), [])):
        configs += fresh
    own = [gd.Model(i, c.family, float(c["rate"]), float(c["l2"])) for i, c in enumerate(configs)]
    sql = f"{gd.training_sql(tasks.task_sql(task), own, k, iterations)} SELECT '{name}' AS run, family, round(rate, 6) AS rate, round(l2, 6) AS l2, round(valid_error, 6) AS valid_error, round(test_error, 6) AS test_error, CAST({models} AS INT) AS models, CAST({models * iterations} AS INT) AS model_iterations FROM m{iterations} m JOIN ({gd.errors_sql(f'm{iterations}', k)}) e ON e.model_id = m.model_id ORDER BY valid_error, m.model_id LIMIT 1"

    @entry(f"plan_{name}", sql)
    def plan(spark: Spark, d: str) -> DataFrame:
        r = run(blocks_of(spark, d, task))
        row = (name, r.config.family, round(float(r.config["rate"]), 6), round(float(r.config["l2"]), 6), round(r.valid_error, 6), round(r.test_error, 6), r.ledger.models, r.ledger.model_iterations)
        return spark.createDataFrame([row], "run string, family string, rate double, l2 double, valid_error double, test_error double, models int, model_iterations int")


_SMALL = {"partial_iters": 4, "max_iters": 12, "batch_size": 8}
_fixed_planner("sequential_grid", tasks.LINE_LINEAR, tiny(), 4, 5, "grid", lambda b: plan_sequential(b, tiny(), Budget(models=4), max_iters=5))
_fixed_planner("sequential_random", tasks.DOC_QUALITY, linear_pair(), 4, 5, "random", lambda b: plan_sequential(b, linear_pair(), Budget(models=4), proposer="random", max_iters=5))
for _n in ("grid", "random", "parzen", "directions", "simplex", "forest", "gaussian_process"):
    _planner(f"adaptive_{_n}", tasks.DOC_QUALITY, lambda b, n=_n: plan_adaptive(b, linear_pair(), Budget(models=16), proposer=n, bandit=Eliminator(), **_SMALL))
_planner("bandit_error_rule", tasks.DOC_QUALITY, lambda b: plan_adaptive(b, linear_pair(), Budget(models=16), proposer="random", bandit=Eliminator(rule="error", tie=0.01), **_SMALL))
_planner("bandit_once", tasks.DOC_QUALITY, lambda b: plan_adaptive(b, linear_pair(), Budget(models=16), proposer="random", bandit=Eliminator(check="once", include_current=True), **_SMALL))
_planner("successive_halving", tasks.DOC_QUALITY, lambda b: plan_adaptive(b, linear_pair(), Budget(models=16), proposer="random", bandit=SuccessiveHalving(), **_SMALL))
_fixed_planner("no_bandit", tasks.DOC_QUALITY, linear_pair(), 16, 12, "random", lambda b: plan_adaptive(b, linear_pair(), Budget(models=16), proposer="random", **_SMALL))
_planner("budget_iterations", tasks.DOC_QUALITY, lambda b: plan_adaptive(b, linear_pair(), Budget(model_iterations=60), proposer="random", bandit=Eliminator(), **_SMALL))
_planner("budget_scans", tasks.DOC_QUALITY, lambda b: plan_adaptive(b, linear_pair(), Budget(scans=8), proposer="random", bandit=Eliminator(), **_SMALL))
_planner("target_error", tasks.DOC_QUALITY, lambda b: plan_adaptive(b, linear_pair(), Budget(models=32, target_error=0.02), proposer="random", bandit=Eliminator(), **_SMALL))
_planner("random_features", tasks.LINE_XOR, lambda b: plan_adaptive(b, random_feature_logistic(5), Budget(models=6), proposer="random", bandit=Eliminator(), partial_iters=4, max_iters=8, batch_size=6))
_planner("kernel_space", tasks.LINE_XOR, lambda b: plan_adaptive(b, kernel_svm(), Budget(models=6), proposer="random", bandit=Eliminator(), partial_iters=4, max_iters=8, batch_size=6))
_planner("warm_start", tasks.DOC_QUALITY, lambda b: plan_adaptive(b, linear_pair(), Budget(models=8), proposer="parzen", bandit=Eliminator(), prior=[Observation(linear_pair().draw(5, i), 0.05 + 0.01 * i) for i in range(20)], **_SMALL))
for _n in ("control_return", "control_status", "control_embedding", "control_event", "control_order"):
    _planner(_n, T[_n], lambda b: plan_adaptive(b, linear_pair(), Budget(models=4), proposer="random", bandit=Eliminator(), partial_iters=3, max_iters=6, batch_size=4), control=True)
_fixed_planner("local_regime", tasks.DOC_QUALITY, linear_pair(), 16, 12, "random", lambda b: plan_adaptive(b, linear_pair(), Budget(models=16), proposer="random", regime="local", **_SMALL))
_planner("first_share", tasks.DOC_QUALITY, lambda b: plan_adaptive(b, linear_pair(), Budget(models=16), proposer="random", bandit=Eliminator(rule="error", tie=0.01), first_share=0.5, **_SMALL))
_planner("components", tasks.EMB_PLANE, lambda b: plan_adaptive(b, component_pipeline(64), Budget(models=12), proposer="random", regime="local", partial_iters=5, max_iters=20, batch_size=12))
_planner("kernel_classes147", tasks.LINE_147, lambda b: plan_adaptive(b, kernel_svm(), Budget(models=2), proposer="random", classes=147, partial_iters=2, max_iters=2, batch_size=2, kernel_features=256))


@entry("plan_history")
def plan_history(spark: Spark, d: str) -> DataFrame:
    """The history of a plan, as the append-only table holds it."""
    r = plan_adaptive(blocks_of(spark, d, tasks.DOC_QUALITY), linear_pair(), Budget(models=12), proposer="parzen", bandit=Eliminator(), **_SMALL)
    return r.history_frame(spark).drop("seconds")


@entry("ensemble_vote")
def ensemble_vote(spark: Spark, d: str) -> DataFrame:
    b = blocks_of(spark, d, tasks.DOC_QUALITY)
    columns = [column_of(linear_pair().draw(3, i), i, 4, 1, 0) for i in range(6)]
    shared_scan.train(b, columns, 8)
    patterns, counts = votes(b, columns)
    members, error = greedy(patterns, counts)
    singles = [1 - counts[np.arange(len(patterns)), patterns[:, k]].sum() / counts.sum() for k in range(6)]
    return spark.createDataFrame([("vote", [int(m) for m in members], float(error)), ("best_single", [int(np.argmin(singles))], float(min(singles)))], "kind string, members array<int>, valid_error double")


@entry("pca_step")
def pca_step(spark: Spark, d: str) -> DataFrame:
    """Dimensionality reduction before training: components of the 64 embedding columns."""
    from pyspark.ml.feature import PCA
    from pyspark.ml.functions import array_to_vector

    df = tasks.load(spark, d, tasks.EMB_PLANE).filter("split = 'train'").withColumn("features", array_to_vector("features"))
    v = PCA(k=5, inputCol="features", outputCol="z").fit(df).explainedVariance.toArray()
    return spark.createDataFrame([(i, round(float(x), 6)) for i, x in enumerate(v)], "component int, variance double")


# --- predictive queries ------------------------------------------------------------------------------


def _session(spark: Spark) -> Session:
    return Session(spark, space=ModelSpace((linear_pair().families[1],)), budget=Budget(models=8), proposer="random", partial_iters=10, max_iters=40, batch_size=8, key=("doc_id",))


def _predictive(name: str, sql: str) -> None:
    @entry(name)
    def run(spark: Spark, d: str) -> DataFrame:
        register(spark, d, "documents", "labels", "lineitem")
        spark.sql("SELECT * FROM documents JOIN labels USING (doc_id)").createOrReplaceTempView("labelled")
        return predict_sql(_session(spark), sql)


_predictive("predict_topk", "SELECT doc_id, n_chars, PREDICT(quality, text, n_chars) GIVEN labelled FROM documents WHERE source = 'src1' AND doc_id NOT IN (SELECT doc_id FROM labels) ORDER BY n_chars DESC, doc_id LIMIT 50")
_predictive("predict_filter", "SELECT doc_id, n_chars FROM documents WHERE n_chars > 500 AND PREDICT(lang, text) = 'en' GIVEN (SELECT lang, text FROM documents)")
_predictive("predict_groupby", "SELECT PREDICT(quality, text) GIVEN labelled AS quality, count(*) AS n FROM documents GROUP BY PREDICT(quality, text) GIVEN labelled HAVING count(*) > 0 ORDER BY 1")
_predictive("predict_two_clauses", "SELECT doc_id, PREDICT(quality, text) GIVEN labelled AS q, PREDICT(toxic, text) GIVEN labelled AS t FROM documents")
_predictive("predict_regression", "SELECT l_orderkey, l_linenumber, PREDICT(l_extendedprice, l_quantity, l_discount) GIVEN (SELECT l_extendedprice, l_quantity, l_discount FROM lineitem) AS price FROM lineitem")


def _predicted(spark: Spark, d: str, sql: str) -> DataFrame:
    register(spark, d, "documents", "labels", "lineitem")
    spark.sql("SELECT * FROM documents JOIN labels USING (doc_id)").createOrReplaceTempView("labelled")
    return predict_sql(_session(spark), sql)


@entry("check_predict_topk", "SELECT doc_id, n_chars, TRUE AS known_class FROM documents WHERE source = 'src1' AND doc_id NOT IN (SELECT doc_id FROM labels) ORDER BY n_chars DESC, doc_id LIMIT 50")
def check_predict_topk(spark: Spark, d: str) -> DataFrame:
    """The rows of the ordered query are those of the query without the clause."""
    out = _predicted(spark, d, "SELECT doc_id, n_chars, PREDICT(quality, text, n_chars) GIVEN labelled AS q FROM documents WHERE source = 'src1' AND doc_id NOT IN (SELECT doc_id FROM labels) ORDER BY n_chars DESC, doc_id LIMIT 50")
    return out.select("doc_id", "n_chars", F.col("q").isin(0, 1).alias("known_class"))


@entry("check_predict_filter", "SELECT count(*) AS documents, TRUE AS under_5_percent_wrong FROM documents WHERE n_chars > 500")
def check_predict_filter(spark: Spark, d: str) -> DataFrame:
    """Documents that the predicted language lets through, against the language that is known."""
    out = _predicted(spark, d, "SELECT doc_id, lang, PREDICT(lang, text) GIVEN (SELECT lang, text FROM documents) AS p FROM documents WHERE n_chars > 500")
    return out.agg(F.count(F.lit(1)).alias("documents"), (F.avg(((F.col("p") == "en") != (F.col("lang") == "en")).cast("double")) < 0.05).alias("under_5_percent_wrong"))


@entry("check_predict_groupby", "SELECT count(*) AS n, TRUE AS two_groups FROM documents")
def check_predict_groupby(spark: Spark, d: str) -> DataFrame:
    out = _predicted(spark, d, "SELECT PREDICT(quality, text) GIVEN labelled AS quality, count(*) AS n FROM documents GROUP BY PREDICT(quality, text) GIVEN labelled")
    return out.agg(F.sum("n").alias("n"), (F.count(F.lit(1)) == 2).alias("two_groups"))


@entry("check_predict_two_clauses", "SELECT count(*) AS labelled, TRUE AS quality_beats_majority, TRUE AS toxic_no_worse FROM documents JOIN labels USING (doc_id)")
def check_predict_two_clauses(spark: Spark, d: str) -> DataFrame:
    from ..sources.tables import table

    out = _predicted(spark, d, "SELECT doc_id, PREDICT(quality, text) GIVEN labelled AS q, PREDICT(toxic, text) GIVEN labelled AS t FROM documents")
    wrong = lambda p, y: F.avg((F.col(p) != F.col(y)).cast("double"))
    rare = lambda y: F.least(F.avg(y), 1 - F.avg(y))
    return out.join(table(spark, d, "labels"), "doc_id").agg(F.count(F.lit(1)).alias("labelled"), (wrong("q", "quality") < rare("quality")).alias("quality_beats_majority"), (wrong("t", "toxic") <= rare("toxic")).alias("toxic_no_worse"))


@entry("check_predict_regression", "SELECT count(*) AS n, TRUE AS below_variance FROM lineitem")
def check_predict_regression(spark: Spark, d: str) -> DataFrame:
    out = _predicted(spark, d, "SELECT l_extendedprice, PREDICT(l_extendedprice, l_quantity, l_discount) GIVEN (SELECT l_extendedprice, l_quantity, l_discount FROM lineitem) AS price FROM lineitem")
    return out.agg(F.count(F.lit(1)).alias("n"), (F.avg(F.pow(F.col("price") - F.col("l_extendedprice"), 2)) <= F.var_pop("l_extendedprice") * 1.01).alias("below_variance"))


@entry("predict_recommendation", "SELECT count(*) AS pairs, TRUE AS near_the_mean FROM (SELECT DISTINCT o_custkey, l_partkey FROM orders JOIN lineitem ON o_orderkey = l_orderkey)")
def predict_recommendation(spark: Spark, d: str) -> DataFrame:
    """How often a customer orders a part, by a clause over two identifiers; the counts are nearly all one,
    so the factors must not be far worse than the mean."""
    from ..sources.tables import table

    o, lines = table(spark, d, "orders"), table(spark, d, "lineitem")
    counts = o.join(lines, o["o_orderkey"] == lines["l_orderkey"]).groupBy("o_custkey", "l_partkey").agg(F.count(F.lit(1)).alias("times"))
    counts.createOrReplaceTempView("ordered")
    session = Session(spark, identifiers=("o_custkey", "l_partkey"))
    out = predict_sql(session, "SELECT o_custkey, l_partkey, times, PREDICT(times, o_custkey, l_partkey) GIVEN ordered AS expected FROM ordered")
    error = F.sqrt(F.avg(F.pow(F.col("expected") - F.col("times"), 2)))
    return out.agg(F.count(F.lit(1)).alias("pairs"), (error <= 1.5 * F.stddev_pop("times") + 0.05).alias("near_the_mean"))


@entry("predict_dataframe")
def predict_dataframe(spark: Spark, d: str) -> DataFrame:
    """The DataFrame form with default predictors."""
    from ..sources.tables import table

    docs, labels = table(spark, d, "documents"), table(spark, d, "labels")
    given = docs.join(labels, "doc_id").select("doc_id", "text", "n_chars", "quality")
    return _session(spark).predict(docs.join(labels, "doc_id", "left_anti"), "quality", given=given).select("doc_id", "quality")


@entry("score_linear_sql", "SELECT l_linestatus, CASE WHEN 0.1 + 1.5 * (l_quantity - 25.5) / 14.4 - 0.5 * (l_discount - 0.05) / 0.029 > 0 THEN 'high' ELSE 'low' END AS prediction, count(*) AS n FROM lineitem GROUP BY 1, 2")
def score_linear_sql(spark: Spark, d: str) -> DataFrame:
    """A stored plan applied as an expression."""
    from ..plans.score import Plan, score
    from ..sources.tables import table

    plan = Plan("prediction", ["l_quantity", "l_discount"], ["l_quantity", "l_discount"], [25.5, 0.05], [14.4, 0.029], [[0.1], [1.5], [-0.5]], ["low", "high"])
    return score(table(spark, d, "lineitem"), plan).groupBy("l_linestatus", "prediction").agg(F.count(F.lit(1)).alias("n"))


def flagship(spark: Spark, d: str) -> DataFrame:
    """Adaptive planning of document quality; the unlabelled documents with the predicted column."""
    from ..sources.tables import table

    docs, labels = table(spark, d, "documents"), table(spark, d, "labels")
    session = Session(spark, budget=Budget(models=16), proposer="parzen", partial_iters=5, max_iters=15, batch_size=8, key=("doc_id",))
    scored = session.predict(docs.join(labels, "doc_id", "left_anti"), "quality", ["text", "n_chars"], docs.join(labels, "doc_id"))
    return scored.select("doc_id", "source", "lang", "n_chars", "quality").orderBy(F.desc("n_chars"), "doc_id")


entry("flagship")(flagship)
