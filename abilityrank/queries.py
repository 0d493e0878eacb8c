"""The registered queries of the ranking engine: name -> function of a session and a folder of tables."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import model
from .functions.draws import entropy_of, micros
from .model import OPTION, Opts
from .operators import components as graph
from .operators import consec, fiedler, generate, linalg, metrics, orient, privileged, spectral, truth
from .operators.rank import global_rank, rank_users
from .oracles import ROUNDS
from .plans import workloads
from .plans.storage import written
from .sources import rsets
from .sources.rsets import rset, table
from .streaming import streams

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}


def query(f):
    QUERIES[f.__name__] = f
    return f


def _add(name: str, f) -> None:
    QUERIES[name] = f


def six(column: str, name: str | None = None, digits: int = 6):
    return (F.round(column, digits) + F.lit(0.0)).alias(name or column)


def held(spark: SparkSession, d: str, name: str) -> DataFrame:
    """A response set that several steps read."""
    return written(rset(spark, d, name), name)


def ranked(result: spectral.Result) -> DataFrame:
    return rank_users(written(result.scores, "scores"), 6).select("user_id", "score", "rank")


for _key, _name in {"resp_supplier_brand": "R1", "resp_supplier_part": "R2", "resp_customer_quarter": "R3", "resp_user_day": "R4", "resp_vector_dim": "R5", "resp_doc_features": "R6", "resp_conv_turn": "R7"}.items():
    _add(_key, lambda s, d, n=_name: rset(s, d, n))


def _users(s: SparkSession, d: str) -> DataFrame:
    return generate.users_from(table(s, d, "supplier"), "s_suppkey", "s_acctbal")


def _items(s: SparkSession, d: str) -> DataFrame:
    return generate.items_from(table(s, d, "part"), "p_partkey", 50, 3)


for _key, _name in {"resp_graded": "graded", "resp_nominal": "nominal", "resp_nominal_guess": "nominal_guess", "resp_binary3p": "binary", "resp_step": "step"}.items():
    _add(_key, lambda s, d, n=_name: generate.generate(_users(s, d), _items(s, d), n))
_add("resp_thinned", lambda s, d: generate.generate(_users(s, d), _items(s, d), "graded", answered=0.6))


def supplier_ranks(s: SparkSession, d: str) -> DataFrame:
    return global_rank(table(s, d, "supplier").select(F.col("s_suppkey").cast("long").alias("user_id"), "s_acctbal"), ["s_acctbal", "user_id"], "r").select("user_id", "r")


@query
def resp_consistent(s: SparkSession, d: str) -> DataFrame:
    return generate.consistent(supplier_ranks(s, d), 50)


def consistent_text(s: SparkSession, d: str) -> DataFrame:
    return written(resp_consistent(s, d).select("user_id", F.col("item_id").cast("string").alias("item_id"), F.col("option_id").cast("string").alias("option_id")), "consistent")


_add("passage_items", rsets.passage_items)
_add("page_features", rsets.page_features)
_add("response_stats", lambda s, d: model.response_stats(rset(s, d, "R1")))
_add("item_option_counts", lambda s, d: rset(s, d, "R1").groupBy(*OPTION).agg(F.count("*").alias("n")))
_add("user_degrees", lambda s, d: rset(s, d, "R2").groupBy("user_id").agg(F.count("*").alias("degree")))


@query
def option_entropy(s: SparkSession, d: str) -> DataFrame:
    counts = rset(s, d, "R1").groupBy(*OPTION).agg(F.count("*").alias("n"))
    totals = counts.groupBy("item_id").agg(F.sum("n").alias("total"))
    return counts.join(totals, "item_id").groupBy("item_id").agg(entropy_of(F.col("n") / F.col("total")).alias("entropy")).select("item_id", six("entropy"))


_add("one_hot_edges", lambda s, d: model.one_hot(held(s, d, "R1")))


@query
def wide_matrix(s: SparkSession, d: str) -> DataFrame:
    brands = [f"Brand#{i}{j}" for i in range(1, 6) for j in range(1, 6)]
    wide = model.to_wide(rset(s, d, "R1"), brands)
    return wide.select("user_id", *[F.col(f"`{b}`").alias("b" + b[-2:]) for b in brands])


@query
def packed_rows(s: SparkSession, d: str) -> DataFrame:
    choices = F.transform("choices", lambda c: F.concat(c["item_id"], F.lit("="), c["option_id"]))
    return model.pack(rset(s, d, "R1")).select("user_id", F.array_join(choices, ",").alias("choices"))


@query
def filtered_answers(s: SparkSession, d: str) -> DataFrame:
    return model.filter_min_answers(held(s, d, "R4"), 2, 1).agg(F.count("*").alias("n_answers"), F.countDistinct("user_id").alias("n_users"))


@query
def avg_step(s: SparkSession, d: str) -> DataFrame:
    r = held(s, d, "R1")
    return linalg.avg_step(r, linalg.initial_scores(r))[1].select("user_id", six("score"))


_add("avghits_rounds", lambda s, d: spectral.avghits(held(s, d, "R1"), Opts(rounds=5)).scores.select("user_id", six("score")))
_add("update_matrix", lambda s, d: linalg.update_matrix(held(s, d, "R1")).select("u", "v", six("value")))
_add("diff_update_matrix", lambda s, d: linalg.diff_update_matrix(held(s, d, "R1")).select("i", "j", six("value")))
for _key, _name in {"diffprop_supplier_brand": "R1", "diffprop_customer_quarter": "R3", "diffprop_user_day": "R4"}.items():
    _add(_key, lambda s, d, n=_name: ranked(spectral.diffprop_power(held(s, d, n), Opts(rounds=ROUNDS))))
_add("diffprop_consistent", lambda s, d: ranked(spectral.diffprop_power(consistent_text(s, d), Opts(rounds=ROUNDS))))
_add("diffprop_gram", lambda s, d: ranked(spectral.diffprop_power(held(s, d, "R1"), Opts(rounds=ROUNDS, path="gram"))))
_add("diffprop_arrow", lambda s, d: ranked(spectral.diffprop_power(held(s, d, "R2"), Opts(rounds=4, path="arrow"))))
_add("diffprop_joins", lambda s, d: ranked(spectral.diffprop_power(held(s, d, "R2"), Opts(rounds=4, path="sql"))))
_add("diffprop_diff_step", lambda s, d: ranked(spectral.diffprop_power(held(s, d, "R1"), Opts(rounds=3, path="sql"), step="diff")))
_add("diffprop_deflated", lambda s, d: ranked(spectral.diffprop_deflation(held(s, d, "R1"), Opts(rounds=10))))


def _from_first(s: SparkSession, d: str, scores: DataFrame) -> DataFrame:
    """The order found, in the direction in which the first user stands in the lower half."""
    order = rank_users(written(scores, "scores"), 9, descending=False)
    ends = order.agg(F.min_by("rank", "user_id").alias("a"), F.max("rank").alias("m"))
    return order.crossJoin(F.broadcast(ends)).select("user_id", F.when(F.col("a") * 2 <= F.col("m"), F.col("rank")).otherwise(F.col("m") + 1 - F.col("rank")).alias("rank"))


_add("diffprop_direct", lambda s, d: _from_first(s, d, spectral.diffprop_direct(consistent_text(s, d)).scores))
_add("diffprop_naive", lambda s, d: _from_first(s, d, spectral.diffprop_naive(consistent_text(s, d), Opts(tol=1e-7, max_iter=1_000_000_000)).scores))
_add("fiedler_direct", lambda s, d: _from_first(s, d, fiedler.fiedler_direct(consistent_text(s, d)).scores))
_add("laplacian_edges", lambda s, d: fiedler.laplacian(held(s, d, "R1")))
_add("fiedler_rounds", lambda s, d: ranked(fiedler.fiedler_power(held(s, d, "R1"), Opts(rounds=10))))


@query
def p_matrix_violations(s: SparkSession, d: str) -> DataFrame:
    r = held(s, d, "R1")
    return consec.violations(r, linalg.positions(r).select("user_id", F.col("pos").alias("rank")))


@query
def consistency_check(s: SparkSession, d: str) -> DataFrame:
    found = [("consistent", consec.is_consistent(consistent_text(s, d), "pqtree")), ("supplier_brand", consec.is_consistent(held(s, d, "R1"), "pqtree"))]
    return s.createDataFrame(found, "dataset string, consistent boolean")


_add("duplicate_users", lambda s, d: model.collapse_users(rset(s, d, "R4"))[1].select("kept", "multiplicity").distinct())
_add("components", lambda s, d: graph.components(held(s, d, "R7")))
_add("hits_rounds", lambda s, d: ranked(truth.hits(held(s, d, "R2"), Opts(rounds=ROUNDS))))
_add("truthfinder_rounds", lambda s, d: ranked(truth.truthfinder(held(s, d, "R2"), Opts(rounds=5))))
_add("investment_rounds", lambda s, d: ranked(truth.investment(held(s, d, "R2"))))
_add("pooled_rounds", lambda s, d: ranked(truth.pooled_investment(held(s, d, "R2"))))
_add("participation", lambda s, d: truth.participation(rset(s, d, "R2")))
_add("majority_key", lambda s, d: truth.majority_key(rset(s, d, "R2")))


def _keyed(s: SparkSession, d: str, name: str = "R2") -> tuple[DataFrame, DataFrame]:
    r = held(s, d, name)
    return r, written(truth.majority_key(r), "key")


def _correct(s: SparkSession, d: str) -> DataFrame:
    return truth.true_answer(*_keyed(s, d))


def _agree(s: SparkSession, d: str, name: str = "R2") -> DataFrame:
    return truth.true_answer(*_keyed(s, d, name), rate=True)


_add("true_answer", _correct)
_add("majority_agreement", lambda s, d: _agree(s, d).select("user_id", six("score")))
_add("threshold_select", lambda s, d: truth.threshold_select(*_keyed(s, d), 10))


@query
def graded_estimates(s: SparkSession, d: str) -> DataFrame:
    items = _items(s, d)
    data = written(generate.generate(_users(s, d), items, "graded"), "graded")
    return privileged.graded_estimator(data.withColumn("item_id", F.col("item_id").cast("string")), generate.option_order(items, "graded").withColumn("item_id", F.col("item_id").cast("string"))).scores.select("user_id", six("score", digits=4))


def _propagated(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    r = held(s, d, "R1")
    return r, written(ranked(spectral.diffprop_power(r, Opts(rounds=ROUNDS))), "ranked")


@query
def decile_entropy(s: SparkSession, d: str) -> DataFrame:
    r, c = _propagated(s, d)
    return orient.slice_entropy(r, c).select("side", six("entropy"), "n_items")


@query
def oriented_ranking(s: SparkSession, d: str) -> DataFrame:
    r, c = _propagated(s, d)
    scores, _ = orient.orient_by_entropy(r, c.select("user_id", "score"), digits=6)
    return rank_users(scores, 6).select("user_id", "score", "rank")


@query
def infer_truth(s: SparkSession, d: str) -> DataFrame:
    r, c = _propagated(s, d)
    return truth.infer_truth(r, c).select("item_id", "option_id", six("mean_rank"))


@query
def option_weights(s: SparkSession, d: str) -> DataFrame:
    """Means of six-digit scores, rounded half up in whole numbers: no engine's float sums decide an edge."""
    r, c = _propagated(s, d)
    millionths = F.round(F.col("score") * 1_000_000).cast("long").alias("score")
    sums = r.join(c.select("user_id", millionths), "user_id").groupBy(*OPTION).agg(F.sum("score").alias("s"), F.count("*").alias("n"))
    top, base = F.col("s") * 2 + F.col("n") * 10, F.col("n") * 20
    return sums.withColumn("h", top - F.pmod(top, base)).withColumn("b", base).select(*OPTION, (F.expr("h div b") / 100_000.0).alias("weight"))


@query
def spearman(s: SparkSession, d: str) -> DataFrame:
    r, key = _keyed(s, d)
    return metrics.spearman_df(truth.true_answer(r, key, rate=True), truth.participation(r)).select(six("rho"))


@query
def kendall(s: SparkSession, d: str) -> DataFrame:
    r, key = _keyed(s, d)
    part = truth.participation(r).select("user_id", F.col("score").cast("double").alias("score"))
    return metrics.kendall_df(truth.true_answer(r, key, rate=True), part).select("concordant", "discordant", six("tau"))


@query
def displacement(s: SparkSession, d: str) -> DataFrame:
    r, key = _keyed(s, d)
    return metrics.displacement([rank_users(truth.true_answer(r, key, rate=True)), rank_users(truth.true_answer(r, key).withColumn("score", F.col("score").cast("double")))]).select(six("displacement"))


@query
def eigvec_variance(s: SparkSession, d: str) -> DataFrame:
    scores = table(s, d, "supplier").select(F.col("s_suppkey").cast("long").alias("user_id"), F.col("s_acctbal").alias("score"))
    return metrics.eigvec_variance(scores, linalg.positions(scores)).select(six("variance"))


@query
def auc_quality(s: SparkSession, d: str) -> DataFrame:
    docs = table(s, d, "documents").select(F.col("doc_id").cast("long").alias("user_id"), F.col("n_chars").cast("double").alias("score"))
    labels = table(s, d, "labels").select(F.col("doc_id").cast("long").alias("user_id"), F.col("quality").alias("label"))
    return metrics.auc(docs, labels).select(six("auc"))


_add("mean_correctness", lambda s, d: metrics.mean_correctness(*_keyed(s, d, "R1")).select(six("correctness")))


def _placed(s: SparkSession, d: str) -> DataFrame:
    """Suppliers with their nation and region (a few rows each)."""
    nation = table(s, d, "nation").join(F.broadcast(table(s, d, "region")), F.col("r_regionkey") == F.col("n_regionkey"))
    return table(s, d, "supplier").join(F.broadcast(nation), F.col("n_nationkey") == F.col("s_nationkey")).select(F.col("s_suppkey").cast("long").alias("user_id"), F.col("r_name").alias("region"), F.col("n_name").alias("nation"))


@query
def accuracy_by_region(s: SparkSession, d: str) -> DataFrame:
    return _agree(s, d, "R1").join(_placed(s, d), "user_id").rollup("region", "nation").agg(F.count("*").alias("n_users"), six(F.avg("score"), "agreement"))


_add("topk_users", lambda s, d: _correct(s, d).orderBy(F.desc("score"), "user_id").limit(10))


@query
def topk_per_region(s: SparkSession, d: str) -> DataFrame:
    best = Window.partitionBy("region").orderBy(F.desc("score"), "user_id")
    return _correct(s, d).join(_placed(s, d), "user_id").withColumn("rank", F.row_number().over(best).cast("long")).where("rank <= 3").select("region", "user_id", "score", "rank")


@query
def setops_top_decile(s: SparkSession, d: str) -> DataFrame:
    r, key = _keyed(s, d)
    a = truth.true_answer(r, key).orderBy(F.desc("score"), "user_id").limit(20).select("user_id")
    b = truth.true_answer(r, key, rate=True).withColumn("score", F.round("score", 9)).orderBy(F.desc("score"), "user_id").limit(20).select("user_id")
    parts = {"both": a.intersect(b), "first": a.exceptAll(b), "second": b.exceptAll(a)}
    return reduce(DataFrame.unionByName, [x.select(F.lit(n).alias("part"), "user_id") for n, x in parts.items()])


@query
def asof_answer(s: SparkSession, d: str) -> DataFrame:
    before = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    seen = F.last(F.when(F.col("event_type") == "view", micros("ts")), ignorenulls=True).over(before)
    return table(s, d, "events").select("event_id", "user_id", "event_type", "ts").withColumn("last_view", seen).where("event_type = 'purchase'").select("event_id", "user_id", "last_view")


@query
def interval_answers(s: SparkSession, d: str) -> DataFrame:
    """Pairs of a user's events within six hours: joined by user and six-hour slot, own and next."""
    span = 6 * 3600 * 1_000_000
    e = table(s, d, "events").select("user_id", micros("ts").alias("t")).withColumn("slot", F.floor(F.col("t") / span))
    a = e.select("user_id", F.col("t").alias("t0"), F.explode(F.array("slot", F.col("slot") + 1)).alias("slot"))
    return a.join(e, ["user_id", "slot"]).where((F.col("t") > F.col("t0")) & (F.col("t") <= F.col("t0") + span)).groupBy("user_id").agg(F.count("*").alias("n_pairs"))


@query
def json_props_item(s: SparkSession, d: str) -> DataFrame:
    k = F.from_json("props", "k int")["k"]
    return table(s, d, "events").select("event_type", (k % 10).cast("int").alias("bucket")).groupBy("event_type", "bucket").agg(F.count("*").alias("n"))


@query
def semi_anti_users(s: SparkSession, d: str) -> DataFrame:
    users, orders = table(s, d, "customer").select("c_custkey"), table(s, d, "orders").select(F.col("o_custkey").alias("c_custkey"))
    return reduce(DataFrame.unionByName, [users.join(orders, "c_custkey", how).agg(F.count("*").alias("n")).select(F.lit(name).alias("part"), "n") for name, how in (("with_orders", "left_semi"), ("without_orders", "left_anti"))])


def _last_epoch(df: DataFrame) -> DataFrame:
    last = df.agg(F.max("epoch").alias("last"))
    return df.crossJoin(F.broadcast(last)).where("epoch = last").drop("epoch", "last")


@query
def stream_final_answers(s: SparkSession, d: str) -> DataFrame:
    events = streams.stream_events(s, streams._folder(s, d))
    return _last_epoch(streams.run_to_end(streams.final_answers(events), "complete", "user_id long, item_id string, option_id string"))


@query
def stream_sliding(s: SparkSession, d: str) -> DataFrame:
    events = streams.stream_events(s, streams._folder(s, d))
    return _last_epoch(streams.run_to_end(streams.sliding_counts(events), "complete", "window_start string, event_type string, n long"))


@query
def stream_sessions(s: SparkSession, d: str) -> DataFrame:
    events = streams.stream_events(s, streams._folder(s, d))
    return _last_epoch(streams.run_to_end(streams.sessions(events), "complete", "user_id long, start_us long, n_events long"))


@query
def cost_model(s: SparkSession, d: str) -> DataFrame:
    """Elementary steps on the suppliers' answers, by their users, items and options."""
    m, n, k = (F.col(c).cast("double") for c in ("n_users", "n_items", "max_options"))
    c = workloads.explain_cost(m, n, k, ROUNDS)
    steps = F.array(*[F.struct(F.lit(x).alias("method"), c[x].alias("steps")) for x in ("diffprop_power", "fiedler_direct")])
    return model.response_stats(held(s, d, "R1")).select(F.explode(steps).alias("x")).select("x.method", "x.steps")


_add("exp_vary_n_graded", lambda s, d: workloads.vary(s, d, "n", models=("graded",)))
_add("exp_vary_n_nominal", lambda s, d: workloads.vary(s, d, "n", models=("nominal",)))
_add("exp_vary_n", lambda s, d: workloads.vary(s, d, "n"))
_add("exp_vary_m", lambda s, d: workloads.vary(s, d, "m"))
_add("exp_vary_k", lambda s, d: workloads.vary(s, d, "k"))
_add("exp_difficulty", lambda s, d: workloads.vary(s, d, "difficulty"))
_add("exp_answer_prob", lambda s, d: workloads.vary(s, d, "answered"))
_add("exp_consistent", lambda s, d: workloads.consistent_data(s, d))
_add("exp_stability", lambda s, d: workloads.stability(s))
_add("exp_real", lambda s, d: workloads.without_truth(s, d))
_add("exp_orientation", lambda s, d: workloads.orientation_success(s, d))


def _real(s: SparkSession, d: str) -> DataFrame:
    return workloads.without_truth(s, d).where("metric = 'spearman'").select(F.col("experiment").alias("dataset"), "method", "metric", "value")


@query
def exp_real_means(s: SparkSession, d: str) -> DataFrame:
    return metrics.mean_over(_real(s, d))


@query
def exp_real_wins(s: SparkSession, d: str) -> DataFrame:
    return metrics.wins(_real(s, d).where("value is not null"))
