"""Trainers, planners, catalog, front end and streams on the smallest tables."""

from __future__ import annotations

import os
import shutil
import subprocess
import sys

import numpy as np
import pytest
from pyspark.sql import functions as F

from foretell.operators import relational as R
from foretell.operators import relational_gd as gd
from foretell.operators import shared_scan as ss
from foretell.operators.block_descent import BlockDescent
from foretell.operators.local_fanout import local_fanout
from foretell.operators.random_features import Projection
from foretell.plans import blocks as packed
from foretell.plans import tasks
from foretell.plans.bandit import Eliminator
from foretell.plans.budget import Budget
from foretell.plans.catalog import Catalog
from foretell.plans.planner import plan_adaptive, plan_sequential
from foretell.plans.session import ClauseError, Session
from foretell.plans.space import linear_pair
from foretell.plans.sqlfront import predict_sql
from foretell.sources import synthetic
from foretell.sources.tables import register, table


@pytest.fixture(scope="module")
def line_blocks(spark, small):
    return packed.store(packed.pack(tasks.load(spark, small, tasks.LINE_LINEAR))).cache()


def test_splits_are_disjoint_and_near_their_shares(spark, small):
    t = tasks.load(spark, small, tasks.LINE_LINEAR)
    n = dict(t.groupBy("split").agg(F.count(F.lit(1))).collect())
    total = sum(n.values())
    assert abs(n["train"] / total - 0.7) < 0.03 and abs(n["valid"] / total - 0.2) < 0.03
    assert t.groupBy("key").agg(F.countDistinct("split").alias("k")).filter("k > 1").count() == 0


def test_blocks_keep_every_row(spark, small, line_blocks):
    t = tasks.load(spark, small, tasks.LINE_LINEAR)
    assert line_blocks.agg(F.sum("n")).first()[0] == t.count()


def test_stored_blocks_of_one_file_are_split(spark):
    """A relation packed by one task is not one row group, which only one task could read."""
    import glob

    import pyarrow.parquet as pq

    rows = spark.range(200_000, numPartitions=1).selectExpr("'train' AS split", "CAST(id % 2 AS INT) AS label", "array(CAST(id AS DOUBLE), 1D, 2D, 3D, 4D) AS features")
    b = packed.store(packed.pack(rows))
    (path,) = b.inputFiles()
    (file,) = glob.glob(path.removeprefix("file://"))
    assert pq.ParquetFile(file).num_row_groups == b.count() == 4
    assert b.agg(F.sum("n")).first()[0] == 200_000
    packed.release(b)


def test_shared_scan_equals_relational_descent(spark, small, line_blocks):
    models = [gd.Model(1, "logistic", 0.5, 0.01), gd.Model(2, "svm", 0.2, 0.01)]
    rows = tasks.load(spark, small, tasks.LINE_LINEAR, wide=True).filter("split = 'train'")
    want = {r["model_id"]: [r[w] for w in gd.weights(5)] for r in gd.train(rows, gd.models_table(spark, models, 5), tasks.LINE_LINEAR.names(), 2).collect()}
    columns = [ss.start(ss.Column(m.model_id, m.family, m.rate, m.l2), 5) for m in models]
    ss.train(line_blocks, columns, 2)
    for c in columns:
        assert np.allclose(c.weights[:, 0], want[c.model_id], rtol=1e-9)


def test_batching_changes_only_the_schedule(line_blocks):
    options = {"proposer": "random", "max_iters": 4, "seed": 2}
    one = plan_sequential(line_blocks, linear_pair(), Budget(models=3), **options)
    many = plan_adaptive(line_blocks, linear_pair(), Budget(models=3), partial_iters=4, batch_size=3, bandit=None, **options)
    assert one.config == many.config and one.valid_error == pytest.approx(many.valid_error)
    assert one.ledger.scans == 12 and many.ledger.scans == 4
    assert one.ledger.model_iterations == many.ledger.model_iterations == 12


def test_adaptive_plan_learns_within_its_budget(line_blocks):
    r = plan_adaptive(line_blocks, linear_pair(), Budget(models=8), partial_iters=3, max_iters=9, batch_size=4, bandit=Eliminator())
    assert r.test_error < 0.2 and r.ledger.models == 8 and not r.partial
    assert r.ledger.model_iterations <= 8 * 9
    done = {}
    for rec in r.history:
        done[rec.model_id] = rec.iters_done
    assert sum(done.values()) == r.ledger.model_iterations


def test_local_training_equals_shared_scans(line_blocks):
    make = lambda: [ss.start(ss.Column(i, "logistic", 0.5 + i, 1e-3), 5) for i in range(2)]
    shared = make()
    ss.train(line_blocks, shared, 3)
    local = {r["model_id"]: r["weights"] for r in local_fanout(line_blocks, make(), 3).collect()}
    for c in shared:
        assert np.allclose(c.weights[:, 0], local[c.model_id], rtol=1e-9)


def test_block_descent_lowers_its_objective_and_learns_products(spark, small):
    b = packed.store(packed.pack(tasks.load(spark, small, tasks.LINE_XOR)))
    m = BlockDescent(Projection(5, 128, 3, 0.6), 2, [1e-5], block=64)
    first = m.state(b)[1e-5]["objective"]
    one = m.train(b)[1e-5]
    two = m.train(b)[1e-5]
    assert first >= one["objective"] >= two["objective"] and two["valid_error"] < 0.25


def test_session_reuses_plans_and_checks_attributes(spark, small, tmp_path):
    register(spark, small, "documents", "labels")
    spark.sql("SELECT * FROM documents JOIN labels USING (doc_id)").createOrReplaceTempView("labelled")
    s = Session(spark, Catalog(spark, str(tmp_path / "plans")), budget=Budget(models=4), proposer="random", partial_iters=3, max_iters=6, batch_size=4, key=("doc_id",))
    sql = "SELECT doc_id, PREDICT(quality, text) GIVEN labelled AS q FROM documents WHERE n_chars > 100 ORDER BY doc_id LIMIT 7"
    first = predict_sql(s, sql).collect()
    assert len(first) == 7 and s.planned == 1
    assert predict_sql(s, sql).collect() == first and s.planned == 1
    assert s.catalog.list().count() == 1
    with pytest.raises(ClauseError):
        predict_sql(s, "SELECT PREDICT(nothing, text) GIVEN labelled FROM documents")
    plan = predict_sql(s, "SELECT doc_id FROM documents WHERE n_chars > 500 AND PREDICT(quality, text) = 1 GIVEN labelled")._jdf.queryExecution().executedPlan().toString()
    assert "GreaterThan(n_chars,500)" in plan


def test_joins(spark):
    a = spark.createDataFrame([(1, 10, "x"), (1, 5, "y"), (2, 1, "z")], "k int, t int, name string")
    b = spark.createDataFrame([(1, 4, 0.4), (1, 9, 0.9), (2, 2, 0.2)], "k int, t int, v double")
    got = {r["name"]: r["v"] for r in R.as_of(a, b, ["k"], "t", "t", ["v"]).collect()}
    assert got == {"x": 0.9, "y": 0.4, "z": None}


def test_trailing_sums_take_no_frame_a_row(spark, tmp_path):
    """Equal to a frame of a range of seconds, also without a time, key or value, and before 1970."""
    from pyspark.sql import Window

    from foretell.catalogue.surrounding import window_range

    rows = [(i, ("a", "b", None)[i % 3], None if i % 50 == 7 else (i * i * 37) % 4000 - 2000, None if i % 11 == 3 or i % 3 == 1 and i % 2 else float(i % 13) / 4) for i in range(600)]
    rows += [(600 + i, "c", t, 1.0) for i, t in enumerate((0, 100, 101, 202, 303, -1, -101))]
    df = spark.createDataFrame(rows, "id int, k string, s long, v double")
    w = Window.partitionBy("k").orderBy("s").rangeBetween(-100, 0)
    want = df.select("id", F.count(F.lit(1)).over(w).alias("n"), F.count("v").over(w).alias("values"), F.sum("v").over(w).alias("sum"))
    got = R.trailing(df, "k", F.col("s"), "v", 100).select("id", F.col("_n").alias("n"), F.col("_values").alias("values"), F.when(F.col("_values") > 0, F.col("_sum")).alias("sum"))
    assert sorted(got.collect()) == sorted(want.collect()) and got.count() == len(rows)
    # sums are rounded once: 256 values of hundredths, whose mean ends in a 5 at the tenth place
    cents = spark.range(256).selectExpr("id", "'a' AS k", "id AS s", "IF(id = 0, 4.18, 48.55 + (id % 2) * 0.04) AS v").withColumn("v", F.col("v").cast("double"))
    last = R.trailing(cents, "k", F.col("s"), "v", 300).filter("id = 255").first()
    assert last["_n"] == 256 and last["_sum"] == (418 + 127 * 4855 + 128 * 4859) / 100
    odd = spark.createDataFrame([(0, "a", 0, float("inf")), (1, "a", 1, 1.0), (2, "a", 200, 2.0), (3, "b", 0, float("nan"))], "id int, k string, s long, v double")
    assert [str(r["_sum"]) for r in R.trailing(odd, "k", F.col("s"), "v", 100).orderBy("id").collect()] == ["inf", "inf", "2.0", "nan"]
    # half a million events of one type within a day: frames by the row would add up 10**11 rows
    many = spark.range(500_000).selectExpr("id AS event_id", "timestamp_millis(id * 86) AS ts", "'view' AS event_type", "1.5 AS value")
    many.withColumn("value", F.col("value").cast("double")).write.parquet(str(tmp_path / "events.parquet"))
    out = window_range(spark, str(tmp_path))
    assert out.agg(F.max("n"), F.min("mean"), F.max("mean")).first() == (500_000, 1.5, 1.5)
    assert out.columns == ["event_id", "n", "mean"]
    assert "specifiedwindowframe(RangeFrame, -86400" not in out._jdf.queryExecution().executedPlan().toString()


def test_synthetic_source(spark):
    synthetic.register(spark)
    df = spark.read.format("synthetic_matrix").options(rows="5000", features="4", noise="0.1", partitions="3").load()
    assert df.count() == 5000 and df.select("row").distinct().count() == 5000
    assert 0.2 < df.agg(F.avg("label")).first()[0] < 0.8


def test_entry_and_registry(spark):
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())
    out = e.entry(spark)
    assert out.columns == ["doc_id", "source", "lang", "n_chars", "quality"] and out.count() > 0


def test_table_helper(spark, small):
    assert table(spark, small, "nation").count() == 25


def test_registry_without_the_training_data_operators(tmp_path):
    """With the operators' folder gone the rest still registers, though the pipeline's file is there."""

    from conftest import ROOT

    shutil.copytree(f"{ROOT}/foretell", tmp_path / "foretell", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    for name in ("__spark_entry__.py", "corpus_pipeline.py"):
        if os.path.exists(f"{ROOT}/{name}"):
            shutil.copy(f"{ROOT}/{name}", tmp_path / name)
    code = "import __spark_entry__ as e; q = e.queries(); assert 'score_linear_sql' in q and 'pipeline' not in q and set(e.oracle_sql()) <= set(q)"
    env = {k: v for k, v in os.environ.items() if k != "PYTHONPATH"}
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, env=env, check=True)


def test_partial_sums_are_added_in_bounded_groups(spark):
    from foretell.operators.tree_sum import gather, tree_sum

    rows = spark.range(1000).select(F.lit("grad").alias("kind"), (F.col("id") % 2).alias("part"), F.floor(F.col("id") / 2).alias("task"), F.unhex(F.lit("000000000000F03F" * 3)).alias("payload"))
    out = tree_sum(rows, 500, fan_in=7)
    plan = out._jdf.queryExecution().executedPlan().toString()
    assert plan.count("FlatMapGroupsInArrow") == 4  # 500 -> 72 -> 11 -> 2 -> 1
    assert gather(out.collect(), 3)["grad"].tolist() == [500.0] * 6


def test_local_and_distributed_rounds_agree(line_blocks):
    options = {"proposer": "random", "partial_iters": 3, "max_iters": 6, "batch_size": 4, "bandit": Eliminator(rule="error", tie=0.01)}
    told = []
    far = plan_adaptive(line_blocks, linear_pair(), Budget(models=8), on_improve=told.append, **options)
    near = plan_adaptive(line_blocks, linear_pair(), Budget(models=8), regime="local", **options)
    assert [(r.model_id, r.status, round(r.valid_error, 9)) for r in far.history] == [(r.model_id, r.status, round(r.valid_error, 9)) for r in near.history]
    assert far.test_error == pytest.approx(near.test_error) and near.regime == "local"
    assert [r.valid_error for r in told] == sorted({r.valid_error for r in told}, reverse=True) and told[-1].valid_error <= far.valid_error
    assert far.ledger.held_out_scans > 0 and far.ledger.tables_read == far.ledger.scans
    assert plan_adaptive(line_blocks, linear_pair(), Budget(models=8), regime="auto", **options).regime == "local"


def test_first_stops_on_a_share_of_the_data(spark, small):
    rows = tasks.load(spark, small, tasks.LINE_LINEAR)
    b = packed.store(packed.pack(rows, rows_per_block=100))
    options = {"proposer": "random", "partial_iters": 4, "max_iters": 8, "batch_size": 4, "bandit": None}
    part = plan_adaptive(b, linear_pair(), Budget(models=4), first_share=0.25, **options)
    assert part.ledger.tables_read == pytest.approx(4 * 0.25 + 4) and part.ledger.scans == 8
    # a share without any block: all are read
    assert plan_adaptive(b, linear_pair(), Budget(models=4), first_share=0.0001, **options).ledger.tables_read == 8
    # and a plan without training rows ends
    assert plan_adaptive(b.filter("split <> 'train'"), linear_pair(), Budget(models=4), **options).ledger.models == 4
    packed.release(b)


def test_kernel_models_share_a_projection(spark, small):
    from foretell.plans.planner import KernelModel
    from foretell.plans.space import Family, ModelSpace, Real, component_pipeline, kernel_svm

    b = packed.store(packed.pack(tasks.load(spark, small, tasks.LINE_XOR)))
    space = ModelSpace((Family("gaussian", {"scale": Real(0.5, 0.500001), "skew": Real(0.0, 1e-9), "l2": Real(1e-6, 1e-2, log=True)}),))
    r = plan_adaptive(b, space, Budget(models=4), proposer="grid", partial_iters=2, max_iters=2, batch_size=4, kernel_features=128)
    assert r.valid_error < 0.2 and r.column.weights.shape == (129, 1) and r.test_error < 0.2
    assert plan_adaptive(b, kernel_svm(), Budget(models=2), proposer="random", partial_iters=1, max_iters=2, batch_size=2, kernel_features=64).ledger.models == 2
    assert KernelModel is not None
    c = plan_adaptive(b, component_pipeline(5), Budget(models=4), proposer="random", partial_iters=2, max_iters=4, batch_size=4)
    assert 1 <= c.config["components"] <= 5 and 0 < c.valid_error < 0.7


def test_narrow_kernel_models_take_one_pass(spark, small, monkeypatch):
    """Steps from kept sums equal steps by passes, and a plan reads the training data once a projection."""
    from foretell.operators import block_descent as bd
    from foretell.plans.space import kernel_svm

    b = packed.store(packed.pack(tasks.load(spark, small, tasks.LINE_XOR)))
    l2s = [1e-5, 1e-2]
    slow, fast = (BlockDescent(Projection(5, 96, 3, 0.6), 2, l2s, block=40) for _ in range(2))
    made = []
    for _ in range(4):
        slow.step(b)
        made.append(bd.step_kept(b, [fast]))
    assert made == [True, False, False, False] and fast.passes == slow.passes == 4
    want = slow.state(b)
    for v in l2s:
        assert np.allclose(slow.weights[v], fast.weights[v], rtol=1e-6, atol=1e-8)
        assert fast.objective(v) == pytest.approx(want[v]["objective"], rel=1e-9)
    options = {"proposer": "random", "bandit": None, "partial_iters": 2, "max_iters": 4, "batch_size": 3, "kernel_features": 64}
    quick = plan_adaptive(b, kernel_svm(), Budget(models=3), **options)
    assert quick.ledger.scans == 1 and quick.ledger.model_iterations == 12
    monkeypatch.setattr(bd, "KEPT", 0)
    passes = plan_adaptive(b, kernel_svm(), Budget(models=3), **options)
    assert passes.ledger.scans == 4 and passes.config == quick.config and passes.test_error == quick.test_error
    assert [(r.model_id, r.status, r.valid_error) for r in passes.history] == [(r.model_id, r.status, r.valid_error) for r in quick.history]
    assert [r.train_loss for r in passes.history] == pytest.approx([r.train_loss for r in quick.history])
    # no training rows: the plan still ends
    none = plan_adaptive(b.filter("split <> 'train'"), kernel_svm(), Budget(models=2), **options)
    assert none.ledger.models == 2
    packed.release(b)


def test_clauses_learn_from_words(spark, tmp_path):
    rows = [(i, ("good news today " if i % 2 else "terrible rubbish here ") + f"number {i}", float(i % 7), i % 2) for i in range(400)]
    given = spark.createDataFrame(rows, "id long, text string, x double, label int")
    s = Session(spark, Catalog(spark, str(tmp_path / "plans")), budget=Budget(models=4), proposer="random", max_iters=20, partial_iters=10, batch_size=4, key=("id",))
    scored = s.predict(given.drop("label"), "label", given=given)
    assert scored.join(given.select("id", F.col("label").alias("y")), "id").filter("label <> y").count() == 0
    plan = s.catalog.lookup(s.catalog.list().first()["fingerprint"])
    plan.texts and scored.count()
    small_inline = plan.column()
    import foretell.plans.score as score_module

    kept, score_module.INLINE_SLOTS = score_module.INLINE_SLOTS, 0
    try:
        both = given.select(small_inline.alias("a"), plan.column().alias("b"))
        assert both.filter("a <> b").count() == 0
    finally:
        score_module.INLINE_SLOTS = kept
    assert len(s.catalog.prior(linear_pair())) >= 4


def test_plans_follow_the_data_and_recommendations(spark, tmp_path):
    from foretell.plans.catalog import fingerprint

    path = str(tmp_path / "t")
    spark.range(100).selectExpr("id", "id % 2 as y").write.parquet(path)
    first = fingerprint("y", ["id"], spark.read.parquet(path))
    assert first == fingerprint("y", ["id"], spark.read.parquet(path))
    spark.range(10).selectExpr("id", "id % 2 as y").write.mode("append").parquet(path)
    assert first != fingerprint("y", ["id"], spark.read.parquet(path))
    ratings = spark.createDataFrame([(u, i, float(1 + (u % 3 == i % 3) * 4)) for u in range(60) for i in range(40) if (u * 7 + i * 3) % 4], "u int, i int, stars double")
    ratings.createOrReplaceTempView("ratings")
    s = Session(spark, identifiers=("u", "i"))
    out = predict_sql(s, "SELECT u, i, PREDICT(stars, u, i) GIVEN ratings AS p FROM ratings").toPandas()
    assert abs(out[(out.u % 3 == out.i % 3)].p.mean() - 5) < 0.7 and abs(out[(out.u % 3 != out.i % 3)].p.mean() - 1) < 0.7
    found = next(iter(s.recommenders.values()))
    assert found.valid_error < found.mean_error
