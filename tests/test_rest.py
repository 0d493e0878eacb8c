import numpy as np
import pytest
from pyspark.sql import functions as F

from abilityrank import model, queries
from abilityrank.functions import response_models as M
from abilityrank.functions.draws import uniform_draw
from abilityrank.model import Opts
from abilityrank.operators import components, dense, fiedler, generate, metrics, privileged, spectral, truth
from abilityrank.plans import workloads
from abilityrank.sources import rsets

from fixtures import ROWS, SCHEMA, path_data

SF = "/root/testdata/sf0.001"


def test_draw_is_the_same_everywhere(spark):
    got = spark.range(1).select((uniform_draw(F.lit(7), F.lit(13), 42) * 16.0**13).cast("long").alias("x")).first()["x"]
    assert got == 3223915986953026


def test_validate_and_shapes(spark):
    r = path_data(spark)
    assert model.validate(r) == {"repeated_pairs": 0, "nulls": 0}
    bad = r.union(spark.createDataFrame([(1, "t1", "B"), (5, "t1", None)], SCHEMA))
    assert model.validate(bad) == {"repeated_pairs": 1, "nulls": 1}
    assert model.answered(bad).count() == 13
    assert sorted(map(tuple, model.unpack(model.pack(r)).collect())) == sorted(ROWS)
    wide = model.to_wide(r)
    assert sorted(map(tuple, model.from_wide(wide, "user_id", ["t1", "t2", "t3"]).collect())) == sorted(ROWS)
    assert model.one_hot(r).agg(F.max("option_ix")).first()[0] == 6
    kept, members = model.collapse_users(r.union(r.where("user_id = 2").withColumn("user_id", F.lit(9).cast("long"))))
    assert kept.select("user_id").distinct().count() == 4 and members.where("user_id = 9").first()["kept"] == 2


def test_components_and_refusal(spark):
    r = path_data(spark)
    two = r.union(r.select((F.col("user_id") + 10).alias("user_id"), F.concat(F.lit("z"), "item_id"), "option_id"))
    assert {(x["user_id"], x["component"]) for x in components.components(two).collect()} == {(u, 1) for u in (1, 2, 3, 4)} | {(u, 11) for u in (11, 12, 13, 14)}
    with pytest.raises(ValueError):
        components.require_connected(two)
    assert components.require_connected(two, "largest").select("user_id").distinct().count() == 4
    assert components.require_connected(r).count() == 12


def test_model_probabilities(spark):
    t = spark.range(11).select((F.col("id") / 5.0 - 1).alias("t"))
    a, b = F.array(F.lit(1.0), F.lit(4.0), F.lit(9.0)), F.array(F.lit(-0.3), F.lit(0.1), F.lit(0.4))
    total = lambda p: F.aggregate(p, F.lit(0.0), lambda s, x: s + x)
    for p in (M.p_graded(F.col("t"), F.lit(2.0), b), M.p_nominal(F.col("t"), a, b), M.p_nominal_guess(F.col("t"), a, b), M.p_step(F.col("t"), b)):
        assert all(abs(r[0] - 1) < 1e-12 for r in t.select(total(p)).collect())
    steep = t.select(F.array_max(M.p_graded(F.col("t") + 0.05, F.lit(5000.0), b))).collect()
    assert all(r[0] > 0.999 for r in steep)  # the step model is the limit
    assert M.n_params("nominal", 4) == 6


def test_generated_frequencies(spark):
    users = spark.range(1, 401).select(F.col("id").alias("user_id"), (F.col("id") / 400.0).alias("theta"))
    items = generate.items_from(spark.range(1, 21), "id", 20, 3)
    data = generate.generate(users, items, "graded").cache()
    want = users.crossJoin(items).select(F.avg(F.element_at(M.p_graded(F.col("theta"), F.col("a"), F.col("thresholds")), 3))).first()[0]
    assert abs(data.where("option_id = 2").count() / 8000 - want) < 3 * (0.25 / 8000) ** 0.5
    thin = generate.generate(users, items, "graded", answered=0.3).count()
    assert abs(thin / 8000 - 0.3) < 0.02
    key = generate.answer_key(items, "graded")
    rho = metrics.spearman(truth.true_answer(data, key), users.select("user_id", F.col("theta").alias("score")))
    assert rho > 0.8


def test_estimator_orders_users(spark):
    users = spark.range(1, 61).select(F.col("id").alias("user_id"), (F.col("id") / 30.0 - 1).alias("theta"))
    items = generate.items_from(spark.range(1, 16), "id", 15, 3)
    data = generate.generate(users, items, "graded").withColumn("item_id", F.col("item_id").cast("string"))
    order = generate.option_order(items, "graded").withColumn("item_id", F.col("item_id").cast("string"))
    scores = privileged.graded_estimator(data, order, Opts(rounds=3)).scores
    assert metrics.spearman(scores, users.select("user_id", F.col("theta").alias("score"))) > 0.85


def test_truth_baselines_by_numpy(spark):
    r = path_data(spark)
    c = np.zeros((4, 7))
    options = {o: i for i, o in enumerate(sorted({x[1:] for x in ROWS}))}
    for u, *o in ROWS:
        c[u - 1, options[tuple(o)]] = 1
    s = np.ones(4)
    for _ in range(6):
        s = c @ (c.T @ s)
        s /= np.linalg.norm(s)
    got = [x["score"] for x in truth.hits(r, Opts(rounds=6)).scores.orderBy("user_id").collect()]
    assert np.allclose(got, s)
    s = np.full(4, 0.9)
    for _ in range(3):
        s = (c @ (1 - np.exp(c.T @ np.log(1 - np.minimum(s, 1 - 1e-12))))) / c.sum(1)
    assert np.allclose([x["score"] for x in truth.truthfinder(r, Opts(rounds=3)).scores.orderBy("user_id").collect()], s)
    s = np.ones(4)
    for _ in range(10):
        stake = c * (s / c.sum(1))[:, None]
        i = stake.sum(0)
        s = (stake * i**1.2 / i).sum(1)
        s /= s.max()
    assert np.allclose([x["score"] for x in truth.investment(r).scores.orderBy("user_id").collect()], s)


@pytest.mark.parametrize("name", list(rsets.SETS))
def test_sets_are_valid(spark, name):
    assert model.validate(rsets.rset(spark, SF, name)) == {"repeated_pairs": 0, "nulls": 0}


def test_sources_round_trip(spark, tmp_path):
    r = path_data(spark)
    for fmt in ("parquet", "orc", "json", "csv"):
        rsets.write_ranking(r, f"{tmp_path}/{fmt}", fmt)
        assert sorted(map(tuple, rsets.read_responses(spark, f"{tmp_path}/{fmt}", fmt).collect())) == sorted(ROWS)


def test_plan_of_a_round(spark):
    """The scan is pruned to what is needed."""
    text = rsets.supplier_part(spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "l_comment" not in text and "ReadSchema" in text


def test_late_rows_and_refresh(spark, tmp_path):
    from abilityrank.streaming import streams

    refresher = streams.Refresher(Opts(rounds=2, path="sql"))
    refresher(path_data(spark), 0)
    refresher(spark.createDataFrame([(1, "t1", "B")], SCHEMA), 1)
    assert refresher.versions == 2 and refresher.answers.where("user_id = 1 and item_id = 't1'").first()["option_id"] == "B"
    assert refresher.scores.count() == 4


def test_sql_table_function(spark):
    from abilityrank.functions.sql import rank_each, register_sql

    register_sql(spark)
    both = path_data(spark).withColumn("dataset", F.lit("a")).union(path_data(spark).withColumn("dataset", F.lit("b")))
    both.createOrReplaceTempView("answers_of_two")
    rows = spark.sql("SELECT * FROM ability_rank(TABLE(answers_of_two) PARTITION BY (dataset), 'diffprop')").collect()
    assert len(rows) == 8
    one = [r["user_id"] for r in sorted(rows, key=lambda r: r["rank"])][::2]
    assert one in ([1, 2, 3, 4], [4, 3, 2, 1])
    assert rank_each(both, "dataset", "hits").count() == 8
    assert spark.sql("SELECT uniform_draw('7|13|42') AS x").first()["x"] == pytest.approx(3223915986953026 / 16**13)


def test_one_group_equals_the_rounds_over_frames(spark):
    """What a worker runs for a small data set, against the methods over DataFrames."""
    users = spark.range(1, 31).select(F.col("id").alias("user_id"), (F.col("id") / 15.0 - 1).alias("theta"))
    data = generate.generate(users, generate.items_from(spark.range(1, 21), "id", 20, 3), "nominal_guess", answered=0.9).select("user_id", F.col("item_id").cast("string").alias("item_id"), F.col("option_id").cast("string").alias("option_id"))
    rows = data.toPandas()
    data = spark.createDataFrame(rows).cache()
    a = dense.Answers.of(rows["user_id"].to_numpy(), rows["item_id"].to_numpy(), rows["option_id"].to_numpy())
    frame = lambda result: result.scores.toPandas().sort_values("user_id")["score"].to_numpy()
    assert abs(dense.spearman(dense.diffprop(a), frame(spectral.diffprop_power(data)))) > 0.999
    assert abs(dense.spearman(dense.fiedler(a), frame(fiedler.fiedler_direct(data)))) > 0.999
    assert np.allclose(dense.hits(a, 4), frame(truth.hits(data, Opts(rounds=4))))
    assert np.allclose(dense.truthfinder(a, 3), frame(truth.truthfinder(data, Opts(rounds=3), untied=True)))
    assert np.allclose(dense._invested(a, 1.2, False, 3), frame(truth.investment(data, Opts(rounds=3))))
    assert np.allclose(dense._invested(a, 1.4, True, 3), frame(truth.pooled_investment(data, Opts(rounds=3))))


def test_dense_helpers_by_hand():
    a = dense.Answers.of(*(np.array(x) for x in zip(*ROWS)))
    s = dense.diffprop(a)
    assert np.allclose(np.abs(np.diff(s)) / np.linalg.norm(np.diff(s)), [0.118612, 0.352388, 0.928307], atol=1e-4)
    assert dense.is_consecutive(a, np.array([1, 2, 3, 4])) and not dense.is_consecutive(a, np.array([1, 3, 2, 4]))
    assert dense.slice_entropy(a, np.array([True, True, False, False])) == pytest.approx(0.231049, abs=1e-6)
    assert dense.spearman(np.array([1.0, 1.0]), np.array([1.0, 2.0])) is None
    assert dense.majority(a).sum() == 3
    with pytest.raises(ValueError):
        dense.scores(a, "unknown")


def test_estimator_of_a_group_equals_that_of_a_frame(spark):
    users = spark.range(1, 41).select(F.col("id").alias("user_id"), (F.col("id") / 20.0 - 1).alias("theta"))
    items = generate.items_from(spark.range(1, 13), "id", 12, 3).withColumn("run", F.lit(0))
    data = generate.generate(users.withColumn("run", F.lit(0)), items, "graded", run=True, told=True)
    rows = data.toPandas()
    mine = dense.scores(dense.Answers.of(rows["user_id"].to_numpy(), rows["item_id"].to_numpy(), rows["option_id"].to_numpy()), "graded_estimator", grade=rows["grade"].to_numpy())
    text = lambda df: df.withColumn("item_id", F.col("item_id").cast("string"))
    frame = privileged.graded_estimator(text(data.select("user_id", "item_id", "option_id")), text(generate.option_order(items, "graded"))).scores.toPandas().sort_values("user_id")
    assert np.allclose(mine, frame["score"].to_numpy(), atol=0.02)
    # a scoring step never loses likelihood, and a known curve is found again
    x, prior = privileged.nodes()
    counts = privileged.curves(np.array([2.0]), np.array([[-1.0, 1.5]]), x) * prior[None, :, None] * 1e6
    a, c = privileged.start(np.array([3]))
    for _ in range(12):
        before = privileged._value(a, c, counts, x)[0]
        a, c = privileged.improve(a, c, counts, x)
        assert privileged._value(a, c, counts, x)[0] >= before
    assert a[0] == pytest.approx(2.0, abs=0.02) and c[0] == pytest.approx([-1.0, 1.5], abs=0.03)


def test_runs_are_drawn_as_single_sets(spark):
    runs = workloads._runs(spark, [{"seed": 7, "m": 20, "n": 9, "k": 4, "experiment": "x", "param": "n", "value_of_param": 1.0}, {"seed": 8, "m": 20, "n": 5, "answered": 0.5, "experiment": "x", "param": "n", "value_of_param": 2.0}])
    items = generate.items_of_runs(rsets.table(spark, SF, "part"), "p_partkey", runs)
    one = generate.items_from(rsets.table(spark, SF, "part"), "p_partkey", 8, 4, seed=7)  # ids begin at 0
    assert sorted(map(tuple, items.where("run = 0").select("item_id", "a", "slopes", "places", "thresholds").collect())) == sorted(map(tuple, one.collect()))
    users = generate.users_of_runs(rsets.table(spark, SF, "customer"), "c_custkey", "c_acctbal", runs)
    data = workloads.answers_of_runs(users, items, runs)
    single = generate.generate(generate.users_from(rsets.table(spark, SF, "customer"), "c_custkey", "c_acctbal", 19), one, "nominal_guess", 7)
    assert sorted(map(tuple, data.where("run = 0").select("user_id", "item_id", "option_id").collect())) == sorted(map(tuple, single.collect()))
    assert 0 < data.where("run = 1").count() < 100
    key, order = generate.answer_key(one, "nominal_guess"), generate.option_order(one, "nominal_guess")
    told = data.where("run = 0").join(key.withColumnRenamed("option_id", "right"), "item_id").join(order, ["item_id", "option_id"])
    assert told.where((F.col("correct") != (F.col("option_id") == F.col("right"))) | (F.col("grade") != F.col("correctness_rank"))).count() == 0


def _mean(rows, metric="spearman"):
    return rows[rows.metric == metric].groupby("method")["value"].mean()


def test_accuracy_experiments_behave_as_reported(spark):
    """Which method wins and how the measures move, at three seeds a point."""
    found = workloads.vary(spark, SF, "n", (25, 100), seeds=(1, 2, 3)).toPandas()
    assert set(found[found.metric == "spearman"].method) == set(workloads.METHODS) and (found.n_users == 100).all()
    low, high = (found[found.value_of_param == n] for n in (25.0, 100.0))
    assert _mean(high)["diffprop"] > 0.9 and _mean(high)["diffprop"] > _mean(low)["diffprop"]
    for m in ("fiedler", "hits", "truthfinder", "investment", "pooled_investment", "true_answer"):
        assert _mean(high)["diffprop"] >= _mean(high)[m] - 0.005
    thin = workloads.vary(spark, SF, "answered", (0.6, 1.0), methods=("diffprop", "true_answer"), seeds=(1, 2, 3)).toPandas()
    assert _mean(thin[thin.value_of_param == 1.0])["diffprop"] > _mean(thin[thin.value_of_param == 0.6])["diffprop"] > 0.8
    perfect = workloads.consistent_data(spark, "/root/testdata/sf0.01", (10,)).toPandas()
    assert set(perfect[(perfect.metric == "recovered") & (perfect.value == 1)].method) == {"diffprop", "fiedler"}


def test_stability_and_orientation(spark):
    found = workloads.stability(spark, (2.0, 40.0), (1, 2, 3), 60, 60).toPandas()
    for a in (2.0, 40.0):
        own = found[found.value_of_param == a]
        for metric, sign in (("displacement", 1), ("variance", 1), ("spearman", -1)):
            by = _mean(own, metric)
            assert sign * by["diffprop"] < sign * by["fiedler"], (a, metric, by.to_dict())
    way = workloads.orientation_success(spark, SF, (1, 2, 3, 4), 40).toPandas()
    assert way[way.metric == "rate"]["value"].iloc[0] >= 0.75


def test_wins_means_and_timings(spark):
    rows = [("x", "a", "m", 0.5), ("x", "b", "m", 0.7), ("y", "a", "m", 0.9), ("y", "b", "m", 0.9)]
    df = spark.createDataFrame(rows, "dataset string, method string, metric string, value double")
    assert {(r["method"], r["wins"]) for r in metrics.wins(df).collect()} == {("a", 1), ("b", 1)}
    assert {r["method"]: round(r["mean"], 6) for r in metrics.mean_over(df).collect()} == {"a": 0.7, "b": 0.8}
    r = path_data(spark)
    scores = truth.participation(r).select("user_id", F.col("score").cast("double"))
    assert metrics.pearson(scores, scores) is None  # everybody answered three items
    took = workloads.timed(spark, r, {"gram": lambda x: spectral.diffprop_power(x, Opts(rounds=2)), "refused": lambda x: spectral.diffprop_direct(x, Opts(max_users=2))}, repeats=2).collect()
    assert [(t["variant"], t["repeats"]) for t in took] == [("gram", 2)]


def test_superseded_tables_are_deleted(spark):
    import os

    from abilityrank.plans.storage import shared_root

    root = shared_root(spark).replace("file://", "")
    held = lambda: {x for x in os.listdir(root) if x.startswith("scores-")}
    for run in (lambda r: truth.hits(r, Opts(rounds=4)), lambda r: spectral.diffprop_power(r, Opts(rounds=4, path="sql")), lambda r: fiedler.fiedler_power(r, Opts(rounds=4))):
        before = held()
        assert run(path_data(spark)).scores.count() == 4 and len(held() - before) == 1
    scores = spark.createDataFrame([(1, 0.0), (2, 2.0)], "user_id long, score double")
    assert [r["score"] for r in components.teleport(scores, 0.5).orderBy("user_id").collect()] == [0.5, 1.5]


def test_deflation_schemes_agree(spark):
    r = path_data(spark)
    order = lambda res: [x["user_id"] for x in res.scores.orderBy("score").collect()]
    for scheme in ("annihilate", "symmetrised", "hotelling"):
        assert order(spectral.diffprop_deflation(r, Opts(rounds=10), scheme=scheme)) in ([1, 2, 3, 4], [4, 3, 2, 1])
    with pytest.raises(ValueError):
        spectral.diffprop_deflation(r, scheme="symmetric")
