"""The experiments: accuracy over swept parameters, stability, and sets without a known truth.

An experiment is many small data sets (runs: a point of a sweep and a seed).  All of its answers are
generated in one plan, and each run is one group that a worker ranks by every method, so points,
seeds and methods spread over the cluster and nothing is looped over on the driver.  A run's size is
bounded by its m and n.  Methods run to their tolerance, but for the investment methods, which
have ten rounds.

Each experiment returns rows (experiment, model, method, param, value_of_param, seed, n_users,
n_items, metric, value); n_users and n_items are those found, where tables are smaller than asked.
A measure that is undefined (a side without spread) is null.
"""

from __future__ import annotations

import time
from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pandas as pd
from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..model import OPTION, Opts, SizeGuardError
from ..operators import dense, fiedler, generate, linalg, metrics, orient, privileged, spectral, truth
from ..operators.rank import global_rank
from ..sources import rsets
from .storage import written

RUN = "run int, experiment string, model string, param string, value_of_param double, seed int, m int, n int, k int, a_max double, low double, high double, answered double"
ROWS = ["experiment", "model", "method", "param", "value_of_param", "seed", "n_users", "n_items", "metric", "value"]
UNPRIVILEGED = ("diffprop", "fiedler", "hits", "truthfinder", "investment", "pooled_investment")
METHODS = (*UNPRIVILEGED, "true_answer", "graded_estimator")
RANGES = ((-1.0, 0.0), (-0.75, 0.25), (-0.5, 0.5), (-0.25, 0.75), (0.0, 1.0), (0.25, 1.25), (0.5, 1.5))
SWEEPS = {"n": (25, 50, 100, 200, 400), "m": (25, 50, 100, 200, 400, 1500), "k": (2, 3, 4, 5, 6), "difficulty": RANGES, "answered": (0.2, 0.4, 0.6, 0.8, 1.0)}
SLOPES = (1.0, 2.0, 5.0, 10.0, 20.0, 40.0, 100.0)
REAL_SETS = ("R1", "R2", "R3", "R4", "R5", "R6")


def method_scores(name: str, responses: DataFrame, key: DataFrame | None = None, order: DataFrame | None = None, opts: Opts = Opts()) -> DataFrame:
    """Scores of a method by name for one set of answers of any size; the spectral ones are oriented by entropy."""
    if name == "diffprop":
        return orient.orient_by_entropy(responses, spectral.diffprop_power(responses, opts).scores)[0]
    if name == "fiedler":
        return orient.orient_by_entropy(responses, fiedler.fiedler_power(responses, opts).scores)[0]
    if name == "true_answer":
        return truth.true_answer(responses, key)
    if name == "graded_estimator":
        return privileged.graded_estimator(responses, order).scores
    if name == "truthfinder":
        return truth.truthfinder(responses, opts, untied=True).scores
    if name == "hits":
        return truth.hits(responses, opts).scores
    return {"investment": truth.investment, "pooled_investment": truth.pooled_investment}[name](responses).scores


def _runs(spark: SparkSession, specs: list[dict]) -> DataFrame:
    """One row a run; defaults are those of the accuracy experiments."""
    usual = {"m": 100, "n": 100, "k": 3, "a_max": 10.0, "low": -0.5, "high": 0.5, "answered": 1.0, "seed": 42, "model": "nominal_guess"}
    names = [c.split()[0] for c in RUN.split(", ")]
    return spark.createDataFrame([tuple((usual | s | {"run": i})[c] for c in names) for i, s in enumerate(specs)], RUN)


def answers_of_runs(users: DataFrame, items: DataFrame, runs: DataFrame) -> DataFrame:
    """run, user_id, item_id, option_id, theta, correct, grade of all runs; one plan for each model used."""
    out = None
    for model in generate.MODELS:
        own = runs.where(F.col("model") == model).select("run")
        if not own.limit(1).count():
            continue
        part = generate.generate(users.join(F.broadcast(own), "run"), items.join(F.broadcast(own), "run"), model, F.col("seed"), F.col("answered"), run=True, told=True)
        out = part if out is None else out.unionByName(part)
    return out


SCORES = "run int, method string, n_users int, n_items int, user_id long, theta double, score double, correctness double, seconds double"


def scores_of_runs(answers: DataFrame, n_runs: int, methods=METHODS) -> DataFrame:
    """Every method's scores of every run: each run and method is a group of one worker, bounded by the
    run's size.

    answers: run, user_id, item_id, option_id and, for the methods that are told, correct and grade;
    theta is passed on where it is known."""
    for c, kind in (("theta", "double"), ("correct", "boolean"), ("grade", "int")):
        if c not in answers.columns:
            answers = answers.withColumn(c, F.lit(None).cast(kind))

    def solve(key, pdf):
        run, method = int(key[0]), str(key[1])
        a = dense.Answers.of(pdf["user_id"].to_numpy(), pdf["item_id"].to_numpy(), pdf["option_id"].to_numpy())
        theta = np.full(len(a.users), np.nan)
        theta[a.user] = pdf["theta"].to_numpy(float, na_value=np.nan)
        told = pdf["correct"].notna().all()
        correct = pdf["correct"].to_numpy(float) if told else None
        began = time.perf_counter()
        s = np.asarray(dense.scores(a, method, correct, pdf["grade"].to_numpy(np.int64) if told else None), float)
        took = time.perf_counter() - began
        return pd.DataFrame({"run": run, "method": method, "n_users": len(a.users), "n_items": int(a.item_of.max(initial=-1)) + 1, "user_id": a.users, "theta": theta, "score": s, "correctness": float(correct.mean()) if told else np.nan, "seconds": took})

    each = answers.withColumn("method", F.explode(F.array(*[F.lit(m) for m in methods])))
    return each.repartition(min(1000, n_runs * len(methods)), "run", "method").groupBy("run", "method").applyInPandas(solve, SCORES)


def packed(answers: DataFrame) -> DataFrame:
    """run, user_id, theta and the numbered answers of each user, as ``dense.packed_sets`` reads them; theta
    is null where the answers have none.  Numbers are in order: users who answer alike are summed alike."""
    names = ["run", *OPTION]
    if "theta" not in answers.columns:
        answers = answers.withColumn("theta", F.lit(None).cast("double"))
    book = global_rank(answers.select(*names).distinct(), names, "o").withColumn("i", F.min("o").over(Window.partitionBy("run", "item_id")))
    coded = answers.join(written(book, "options").hint("shuffle_hash"), names).select("run", "user_id", "theta", (F.shiftleft("i", 31) + F.col("o")).alias("code"))
    return written(coded.groupBy("run", "user_id").agg(F.max("theta").alias("theta"), F.sort_array(F.collect_list("code")).alias("codes")), "packed")


def solved(sets: DataFrame, n_runs: int, methods, finish, schema: str, sizes=None) -> DataFrame:
    """finish(run, method, answers, theta, scores) -> columns of the schema, for every run (0 .. n_runs - 1) of the
    packed sets and every method.  Each has a task of its own, in which a set takes twelve bytes an answer; where
    the runs' sizes are given, tasks of larger ones begin first."""
    import pyarrow as pa

    names = [c.split()[0] for c in schema.split(", ")]
    kinds = [{"int": pa.int32(), "long": pa.int64(), "double": pa.float64(), "string": pa.string()}[c.split()[1]] for c in schema.split(", ")]

    def solve(batches):
        for (run, method), a, theta in dense.packed_sets(batches):
            columns = finish(run, methods[method], a, theta, np.asarray(dense.scores(a, methods[method]), float))
            for lo in range(0, len(columns[0]), 1 << 18):
                yield pa.RecordBatch.from_arrays([pa.array(c[lo : lo + (1 << 18)], k) for c, k in zip(columns, kinds)], names)

    each = sets.select("run", F.explode(F.array(*[F.lit(k) for k in range(len(methods))])).alias("method"), "user_id", "theta", "codes")
    turn = np.argsort(np.argsort([-x for x in sizes or [0] * n_runs], kind="stable"))
    place = F.element_at(F.array(*[F.lit(int(x)) for x in turn]), F.col("run") + 1)
    dealt = each.repartitionById(n_runs * len(methods), (place * len(methods) + F.col("method")).cast("int"))
    return dealt.sortWithinPartitions("run", "method", "user_id").mapInArrow(solve, schema)


def _spearman(scores: DataFrame, truth_column: str = "theta") -> DataFrame:
    """run, method, n_users, n_items, value: rank correlation within each run, ties averaged; null without spread."""
    by = Window.partitionBy("run", "method")
    rank = lambda c: F.rank().over(by.orderBy(c)) + (F.count("*").over(Window.partitionBy("run", "method", c)) - 1) / 2.0
    rounded = scores.select("run", "method", "n_users", "n_items", (F.round("score", 9) + F.lit(0.0)).alias("s"), (F.round(truth_column, 9) + F.lit(0.0)).alias("t"))
    finite = F.min((~F.isnan("s") & F.col("s").isNotNull()).cast("int"))
    return rounded.withColumn("x", rank("s")).withColumn("y", rank("t")).groupBy("run", "method").agg(F.max("n_users").alias("n_users"), F.max("n_items").alias("n_items"), F.when(finite == 1, metrics.correlation("x", "y")).alias("value"))


def _named(measured: DataFrame, runs: DataFrame, metric: str) -> DataFrame:
    return measured.withColumn("metric", F.lit(metric)).join(F.broadcast(runs.select("run", "experiment", "model", "param", "value_of_param", "seed")), "run").select(*ROWS)


def accuracy(spark: SparkSession, d: str, specs: list[dict], methods=METHODS) -> DataFrame:
    """Spearman of every method in every run, with customers as users and parts as items."""
    runs = _runs(spark, specs)
    users = generate.users_of_runs(rsets.table(spark, d, "customer"), "c_custkey", "c_acctbal", runs)
    items = generate.items_of_runs(rsets.table(spark, d, "part"), "p_partkey", runs)
    scores = written(scores_of_runs(answers_of_runs(users, items, runs), len(specs), methods), "scores")
    share = scores.groupBy("run").agg(F.max("n_users").alias("n_users"), F.max("n_items").alias("n_items"), F.max("correctness").alias("value")).withColumn("method", F.lit("answers"))
    return _named(_spearman(scores), runs, "spearman").unionByName(_named(share, runs, "correctness"))


def vary(spark: SparkSession, d: str, param: str, values=None, models=("nominal_guess",), methods=METHODS, seeds=(42,), **fixed) -> DataFrame:
    """Accuracy with one of n, m, k, difficulty (pairs) or answered swept and the others fixed."""
    specs = []
    for model in models:
        for v in values or SWEEPS[param]:
            own = {"low": v[0], "high": v[1]} if param == "difficulty" else {param: int(v) if param in "mnk" else float(v)}
            specs += [{"experiment": f"vary_{param}", "model": model, "param": param, "value_of_param": float(v[0] if param == "difficulty" else v), "seed": s} | fixed | own for s in seeds]
    return accuracy(spark, d, specs, methods)


def consistent_data(spark: SparkSession, d: str, values=(10, 25, 50, 100), methods=UNPRIVILEGED) -> DataFrame:
    """Data with a perfect order of the suppliers: |rho| and whether the order found makes all options consecutive."""
    users = written(global_rank(rsets.table(spark, d, "supplier").select(F.col("s_suppkey").cast("long").alias("user_id"), "s_acctbal"), ["s_acctbal", "user_id"], "r").select("user_id", "r"), "users")
    runs = _runs(spark, [{"experiment": "consistent", "model": "step", "param": "n", "value_of_param": float(n), "n": n} for n in values])
    parts = [generate.consistent(users, n).withColumn("run", F.lit(i)) for i, n in enumerate(values)]
    answers = parts[0]
    for p in parts[1:]:
        answers = answers.unionByName(p)
    answers = answers.join(users.select("user_id", F.col("r").cast("double").alias("theta")), "user_id")

    def finish(run, method, a, theta, s):
        rho = dense.spearman(s, theta)
        return [[run], [method], [len(a.users)], [int(a.item_of.max()) + 1], [None if rho is None else abs(rho)], [float(dense.is_consecutive(a, dense.descending(a, s)))]]

    found = written(solved(packed(answers), len(values), methods, finish, "run int, method string, n_users int, n_items int, rho double, recovered double", values), "consistent")
    rho, recovered = (found.withColumn("value", F.col(c)).drop("rho", "recovered") for c in ("rho", "recovered"))
    return _named(rho, runs, "spearman").unionByName(_named(recovered, runs, "recovered"))


def stability(spark: SparkSession, slopes=SLOPES, seeds=tuple(range(1, 11)), m: int = 100, n: int = 100, k: int = 3) -> DataFrame:
    """Variance of difference vectors, displacement between seeds and accuracy, by slope; directions are
    settled by the true order."""
    specs = [{"experiment": "stability", "param": "a", "value_of_param": a, "a_max": a, "seed": s, "m": m, "n": n, "k": k} for a in slopes for s in seeds]
    runs = _runs(spark, specs)
    users, items = generate.evenly_spaced_runs(runs.select("run", "m", "n", "k", "a_max", "seed", "answered"))
    raw = written(scores_of_runs(answers_of_runs(users, items, runs), len(specs), ("diffprop", "fiedler")), "scores")
    way = _spearman(raw).select("run", "method", F.when(F.col("value") < 0, -1.0).otherwise(1.0).alias("way"))
    scores = written(raw.join(way, ["run", "method"]).withColumn("score", F.col("score") * F.col("way")).drop("way"), "scores")
    order = Window.partitionBy("run", "method").orderBy("theta", "user_id")
    diffs = scores.withColumn("diff", F.lead("score").over(order) - F.col("score")).where("diff is not null")
    spread = diffs.groupBy("run", "method").agg(F.max("n_users").alias("n_users"), F.max("n_items").alias("n_items"), F.try_divide(F.var_pop("diff"), F.sum(F.col("diff") * F.col("diff"))).alias("value"))
    best = Window.partitionBy("run", "method").orderBy(F.desc(F.round("score", 9)), "user_id")
    ranks = scores.withColumn("rank", F.row_number().over(best)).join(F.broadcast(runs.select("run", "value_of_param", "seed")), "run").select("method", "value_of_param", "seed", "user_id", "rank", "n_users", "n_items")
    other = ranks.select("method", "value_of_param", "user_id", F.col("seed").alias("seed2"), F.col("rank").alias("rank2"))
    moved = ranks.join(other, ["method", "value_of_param", "user_id"]).where("seed < seed2").groupBy("method", "value_of_param").agg(F.max("n_users").alias("n_users"), F.max("n_items").alias("n_items"), (F.avg(F.abs(F.col("rank") - F.col("rank2"))) / F.max("n_users")).alias("value"))
    displaced = moved.select(F.lit("stability").alias("experiment"), F.lit("nominal_guess").alias("model"), "method", F.lit("a").alias("param"), "value_of_param", F.lit(None).cast("int").alias("seed"), "n_users", "n_items", F.lit("displacement").alias("metric"), "value")
    return _named(_spearman(scores), runs, "spearman").unionByName(_named(spread, runs, "variance")).unionByName(displaced)


SCORES_BY_USER = "run int, method string, n_users int, n_items int, user_id long, score double"


def _by_user(run: int, method: str, a: dense.Answers, theta: np.ndarray, s: np.ndarray) -> list:
    each = lambda x: np.full(len(s), x, np.int32)
    return [each(run), [method] * len(s), each(len(a.users)), each(int(a.item_of.max(initial=-1)) + 1), a.users, s]


def without_truth(spark: SparkSession, d: str, sets=REAL_SETS, methods=UNPRIVILEGED) -> DataFrame:
    """Agreement of every method with true_answer under a majority key, and the AUC of document
    rankings against labelled quality.  Sets within the bound of one task are ranked side by side,
    larger ones by the methods' rounds over DataFrames: the same methods to the same tolerances."""
    runs = _runs(spark, [{"experiment": name, "model": "none", "param": "set", "value_of_param": float(i)} for i, name in enumerate(sets)])
    small, parts = None, []

    def held(name):
        data = written(rsets.rset(spark, d, name), "set")
        return data, data.count()

    with ThreadPoolExecutor(3) as pool:  # the sets' tasks fill each other's gaps
        made = list(pool.map(inheritable_thread_target(spark)(held), sets))
    for i, (data, n_answers) in enumerate(made):
        if n_answers <= dense.MOST_PACKED:
            one = data.withColumn("run", F.lit(i))
            small = one if small is None else small.unionByName(one)
            continue
        proxy = truth.true_answer(data, truth.majority_key(data)).select("user_id", F.col("score").cast("double").alias("theta"))
        sizes = data.agg(F.countDistinct("user_id").cast("int").alias("n_users"), F.countDistinct("item_id").cast("int").alias("n_items"))
        for m in methods:
            scores = method_scores(m, data).join(proxy, "user_id").crossJoin(F.broadcast(sizes))
            parts.append(written(scores.select(F.lit(i).alias("run"), F.lit(m).alias("method"), "n_users", "n_items", "user_id", "theta", "score"), "scores"))
    if small is not None:
        found = written(solved(packed(small), len(sets), (*methods, "majority_agreement"), _by_user, SCORES_BY_USER, [n for _, n in made]), "scores")
        proxy = found.where("method = 'majority_agreement'").select("run", "user_id", F.col("score").alias("proxy"))
        parts.append(found.where("method <> 'majority_agreement'").join(proxy, ["run", "user_id"]).select("run", "method", "n_users", "n_items", "user_id", F.col("proxy").alias("theta"), "score"))
    scores = parts[0]
    for p in parts[1:]:
        scores = scores.unionByName(p)
    scores = written(scores, "scores")
    out = _named(_spearman(scores), runs, "spearman")
    if "R6" in sets:
        labels = rsets.table(spark, d, "labels").where("quality is not null").select(F.col("doc_id").cast("long").alias("user_id"), F.col("quality").alias("label"))
        documents = scores.where(F.col("run") == list(sets).index("R6")).join(labels, "user_id")
        by = Window.partitionBy("method")
        rank = F.rank().over(by.orderBy(F.round("score", 9))) + (F.count("*").over(Window.partitionBy("method", F.round("score", 9))) - 1) / 2.0
        good, bad = F.sum((F.col("label") == 1).cast("long")), F.sum((F.col("label") == 0).cast("long"))
        area = documents.withColumn("r", rank).groupBy("run", "method").agg(F.max("n_users").alias("n_users"), F.max("n_items").alias("n_items"), F.try_divide(F.sum(F.when(F.col("label") == 1, F.col("r"))) - good * (good + 1) / 2.0, (good * bad).cast("double")).alias("value"))
        out = out.unionByName(_named(area, runs, "auc"))
    return out


def orientation_success(spark: SparkSession, d: str, seeds=tuple(range(1, 21)), n: int = 100) -> DataFrame:
    """Whether entropy picks the able end, by seed, and the share of seeds where it does."""
    found = accuracy(spark, d, [{"experiment": "orientation", "param": "seed", "value_of_param": float(s), "seed": s, "n": n} for s in seeds], ("diffprop",)).where("metric = 'spearman'")
    each = found.withColumn("metric", F.lit("right_way")).withColumn("value", (F.col("value") > 0).cast("double"))
    rate = each.groupBy("experiment", "model", "method", "param").agg(F.max("n_users").alias("n_users"), F.max("n_items").alias("n_items"), F.avg("value").alias("value"))
    return each.unionByName(rate.select("experiment", "model", "method", "param", F.lit(None).cast("double").alias("value_of_param"), F.lit(None).cast("int").alias("seed"), "n_users", "n_items", F.lit("rate").alias("metric"), "value"))


def scaled_users(spark: SparkSession, m: int, n: int, k: int = 3, seed: int = 42) -> DataFrame:
    """Answers of m generated users to n items for timings; nothing is read."""
    users = spark.range(1, m + 1).select(F.col("id").alias("user_id"), (F.col("id") / F.lit(float(m))).alias("theta"))
    items = generate.items_from(spark.range(1, n + 1), "id", n, k, seed=seed)
    return generate.generate(users, items, "graded", seed).withColumn("item_id", F.col("item_id").cast("string"))


def timed(spark: SparkSession, responses: DataFrame, variants: dict, repeats: int = 5, limit_s: float = 1000.0) -> DataFrame:
    """Median seconds of each variant (name -> function of answers to a Result); stops at the limit."""
    rows = []
    for name, run in variants.items():
        took = []
        for _ in range(repeats):
            began = time.perf_counter()
            try:
                run(responses).scores.write.format("noop").mode("overwrite").save()
            except SizeGuardError:
                break
            took.append(time.perf_counter() - began)
            if took[-1] > limit_s:
                break
        if took:
            rows.append((name, sorted(took)[len(took) // 2], len(took)))
    return spark.createDataFrame(rows, "variant string, seconds double, repeats int")


def explain_cost(m, n, k, t) -> dict:
    """Elementary steps of each method for m users, n items, k options and t rounds; numbers or columns."""
    return {
        "diffprop_power": m * n * t, "diffprop_gram": m * n * n + (n * k) ** 2 * t, "diffprop_direct": m * m * n, "diffprop_naive": m * m * n + m * m * t, "diffprop_deflation": 2 * m * n * t,
        "fiedler_direct": m * m * n, "fiedler_power_printed": m * n * t + m * m * t, "fiedler_power": m * n * t, "pqtree": m * n, "hits": m * n * t, "truthfinder": m * n * t, "investment": m * n * t, "pooled_investment": m * n * t,
    }
