"""Truth-discovery baselines: each has one aggregate towards options and one back to users."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..model import OPTION, Opts
from ..plans.storage import derived, forget, written
from . import linalg
from .spectral import Result

FIXED_ROUNDS = 10


def _normalised(scores: DataFrame, how: str) -> DataFrame:
    kept = written(scores, "scores")
    size = kept.agg({"l2": F.sqrt(F.sum(F.col("score") * F.col("score"))), "max": F.max("score")}[how]).first()[0]
    return derived(kept.select("user_id", (F.col("score") / F.lit(size or 1.0)).alias("score")), kept)


def _rounds(responses: DataFrame, start: float, step, opts: Opts, default: int | None) -> Result:
    """Answers are laid out by user once, with the user's number of them (``n``); a round writes one table of
    scores and deletes the one before."""
    degree = F.count("*").over(Window.partitionBy("user_id"))
    rows = responses.repartition("user_id").withColumn("n", degree).persist()
    n_options = rows.select(*OPTION).distinct().count()
    scores = rows.select("user_id").distinct().withColumn("score", F.lit(start))
    limit = opts.rounds if opts.rounds is not None else default or opts.max_iter
    k = 0
    for k in range(1, limit + 1):
        new, change = step(rows, scores, n_options), None
        if opts.rounds is None and default is None:
            change = new.join(scores.withColumnRenamed("score", "old"), "user_id").agg(F.sqrt(F.sum(F.pow(F.col("score") - F.col("old"), 2)))).first()[0]
        forget(scores)
        scores = new
        if change is not None and change < opts.tol:
            break
    return Result(scores, k)


def hits(responses: DataFrame, opts: Opts = Opts()) -> Result:
    """Sums both ways, length 1: the top eigenvector of co-answering."""
    return _rounds(responses, 1.0, lambda r, s, k: _normalised(linalg.user_sums(r, linalg.option_sums(r, s), k), "l2"), opts, None)


def option_beliefs(rows: DataFrame, scores: DataFrame, floor: float = 1e-12) -> DataFrame:
    """The chance that not all choosers are wrong, by logarithms; log_odds keeps apart what rounds to 1."""
    miss = F.sum(F.log(F.greatest(1.0 - F.col("score"), F.lit(floor))))
    return rows.join(scores, "user_id").groupBy(*OPTION).agg((1.0 - F.exp(miss)).alias("weight"), (-miss).alias("log_odds"))


def truthfinder(responses: DataFrame, opts: Opts = Opts(), start: float = 0.9, untied: bool = False) -> Result:
    """Trust is the mean belief in the options picked.  With many choosers beliefs round to 1 and
    trust ties; ``untied`` gives the mean log-odds of the options in the end, in the same order."""
    out = _rounds(responses, start, lambda r, s, k: written(linalg.user_means(r, option_beliefs(r, s).select(*OPTION, "weight"), k), "scores"), opts, None)
    if untied:
        odds = option_beliefs(responses, out.scores).select(*OPTION, F.col("log_odds").alias("weight"))
        return Result(linalg.user_means(responses, odds), out.rounds)
    return out


def _invest(rows: DataFrame, scores: DataFrame, n_options: int, power: float, pooled: bool) -> DataFrame:
    stakes = rows.join(scores, "user_id").select("user_id", *OPTION, (F.col("score") / F.col("n")).alias("stake"))
    options = stakes.groupBy(*OPTION).agg(F.sum("stake").alias("invested")).withColumn("grown", F.pow("invested", F.lit(power)))
    if pooled:
        item = Window.partitionBy("item_id")
        options = options.withColumn("value", F.coalesce(F.try_divide(F.col("invested") * F.col("grown"), F.sum("grown").over(item)), F.lit(0.0)))
    else:
        options = options.withColumn("value", F.col("grown"))
    gains = linalg._back(stakes, options, n_options).groupBy("user_id").agg(F.coalesce(F.sum(F.try_divide(F.col("value") * F.col("stake"), F.col("invested"))), F.lit(0.0)).alias("score"))
    return _normalised(gains, "max")


def investment(responses: DataFrame, opts: Opts = Opts(), power: float = 1.2) -> Result:
    """Trust is spread over picks, grows there and is paid back by share; a fixed number of rounds."""
    return _rounds(responses, 1.0, lambda r, s, k: _invest(r, s, k, power, False), opts, FIXED_ROUNDS)


def pooled_investment(responses: DataFrame, opts: Opts = Opts(), power: float = 1.4, reverse: bool = False) -> Result:
    """As investment, with an item's total kept and only its shares grown."""
    out = _rounds(responses, 1.0, lambda r, s, k: _invest(r, s, k, power, True), opts, FIXED_ROUNDS)
    return Result(out.scores.withColumn("score", -F.col("score")), out.rounds) if reverse else out


def participation(responses: DataFrame) -> DataFrame:
    return responses.groupBy("user_id").agg(F.count("*").alias("score"))


def threshold_select(responses: DataFrame, key: DataFrame, least_answers: int, least_rate: float | None = None) -> DataFrame:
    """Users with enough answers and a high enough share of correct ones; without ``least_rate`` at least
    the share of all answers together, compared in whole numbers."""
    correct = responses.join(key.withColumnRenamed("option_id", "right_option"), "item_id", "left")
    per = correct.groupBy("user_id").agg(F.count("*").alias("answers"), F.sum(F.coalesce((F.col("option_id") == F.col("right_option")).cast("long"), F.lit(0))).alias("correct"))
    enough = per.where(F.col("answers") >= least_answers)
    if least_rate is not None:
        return enough.where(F.col("correct") >= least_rate * F.col("answers"))
    per = written(per, "correct")
    total = per.agg(F.sum("answers").alias("all_answers"), F.sum("correct").alias("all_correct"))
    return per.where(F.col("answers") >= least_answers).crossJoin(F.broadcast(total)).where("correct * all_answers >= all_correct * answers").select("user_id", "answers", "correct")


def majority_key(responses: DataFrame) -> DataFrame:
    """item_id and its most frequent option; the smallest among equals."""
    counts = responses.groupBy(*OPTION).agg(F.count("*").alias("n"))
    best = Window.partitionBy("item_id").orderBy(F.desc("n"), "option_id")
    return counts.withColumn("r", F.row_number().over(best)).where("r = 1").select("item_id", "option_id")


def true_answer(responses: DataFrame, key: DataFrame, rate: bool = False) -> DataFrame:
    """user_id, score: correct answers, or their share of those given; for users without any too."""
    joined = responses.join(key.withColumnRenamed("option_id", "right_option"), "item_id", "left")
    correct = F.coalesce((F.col("option_id") == F.col("right_option")).cast("long"), F.lit(0))
    return joined.groupBy("user_id").agg((F.avg(correct.cast("double")) if rate else F.sum(correct)).alias("score"))


def majority_agreement(responses: DataFrame) -> DataFrame:
    return true_answer(responses, majority_key(responses), rate=True)


def infer_truth(responses: DataFrame, ranking: DataFrame) -> DataFrame:
    """item_id and the option whose choosers stand best on average; ranking: rank 1 is best."""
    means = responses.join(ranking.select("user_id", "rank"), "user_id").groupBy(*OPTION).agg(F.avg(F.col("rank").cast("double")).alias("mean_rank"))
    best = Window.partitionBy("item_id").orderBy("mean_rank", "option_id")
    return means.withColumn("r", F.row_number().over(best)).where("r = 1").select("item_id", "option_id", "mean_rank")
