"""Accuracy and stability measures."""

from __future__ import annotations

from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..plans.storage import written
from . import linalg
from .rank import global_rank


def correlation(x: str, y: str) -> Column:
    """Pearson's, null where a side is constant (a plain ``corr`` divides by zero in ANSI mode)."""
    return F.try_divide(F.covar_pop(x, y), F.stddev_pop(x) * F.stddev_pop(y))


def average_ranks(scores: DataFrame, name: str = "r", digits: int = 9) -> DataFrame:
    """user_id and its rank, the mean rank for equal scores; counted by distinct score, so the
    running sum is over distinct scores only, in ranges."""
    rounded = scores.select("user_id", (F.round(F.col("score").cast("double"), digits) + F.lit(0.0)).alias("score"))
    ranked = global_rank(rounded, ["score", "user_id"], "_pos")
    return ranked.join(ranked.groupBy("score").agg(F.avg("_pos").alias(name)), "score").select("user_id", name)


def spearman_df(predicted: DataFrame, truth: DataFrame, digits: int = 9) -> DataFrame:
    """One row: rho, over the users that both have."""
    return average_ranks(predicted, "x", digits).join(average_ranks(truth, "y", digits), "user_id").agg(correlation("x", "y").alias("rho"))


def spearman(predicted: DataFrame, truth: DataFrame, digits: int = 9) -> float | None:
    return spearman_df(predicted, truth, digits).first()["rho"]


def pearson(predicted: DataFrame, truth: DataFrame) -> float | None:
    return predicted.join(truth.select("user_id", F.col("score").alias("truth")), "user_id").agg(correlation("score", "truth")).first()[0]


def kendall_df(predicted: DataFrame, truth: DataFrame, block: int = 200_000) -> DataFrame:
    """One row: concordant and discordant pairs and tau-b, for any number of users.

    Discordant pairs are the inversions between two orders in which ties of one score stand by the other;
    pairs tied in one or both come from the sizes of groups, and the rest is concordant."""
    both = written(predicted.select("user_id", "score").join(truth.select("user_id", F.col("score").alias("truth")), "user_id"), "both")
    order = global_rank(both, ["score", "truth", "user_id"], "p")
    order = global_rank(order, ["truth", "score", "user_id"], "q").select("p", "q")
    n, discordant = inverted_pairs(order, block)

    def tied(*by):
        return int(both.groupBy(*by).agg((F.count("*") * (F.count("*") - 1) / 2).cast("long").alias("n")).agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0])

    pairs, x, y, xy = n * (n - 1) // 2, tied("score"), tied("truth"), tied("score", "truth")
    concordant = pairs - x - y + xy - discordant
    spread = float(pairs - x) * (pairs - y)
    row = (concordant, discordant, (concordant - discordant) / spread**0.5 if spread else None) if n > 1 else (None, None, None)
    return predicted.sparkSession.createDataFrame([row], "concordant long, discordant long, tau double")


def inversions(v: np.ndarray) -> int:
    """Pairs in the wrong order, by merging sorted halves, all pairs of halves of a width at once."""
    n = len(v)
    x, at = np.argsort(np.argsort(v, kind="stable"), kind="stable"), np.arange(n)
    total, width = 0, 1
    while width < n:
        block = at // (2 * width)
        keyed = x + block * n
        left = at // width % 2 == 0
        ends = np.searchsorted(at[left], (block[~left] + 1) * 2 * width)  # of the left halves up to this block
        total += int((ends - np.searchsorted(keyed[left], keyed[~left])).sum())
        x = np.sort(keyed) - block * n
        width *= 2
    return total


def inverted_pairs(ranked: DataFrame, block: int) -> tuple[int, int]:
    """(rows, pairs that stand one way by p and the other by q), for positions p and q from 1 on: pairs within a
    block of either order are counted where the block is, those apart in both from the numbers of
    users by pair of blocks, (users / block) squared of them."""
    cells = ranked.select("p", "q", F.floor((F.col("p") - 1) / block).cast("int").alias("bp"), F.floor((F.col("q") - 1) / block).cast("int").alias("bq"))
    n = ranked.count()
    if n < 2:
        return n, 0

    def inside(axis, value):
        def count(pdf: pd.DataFrame) -> pd.DataFrame:
            order = pdf.sort_values(axis)
            v, other = order[value].to_numpy(), order["bp"].to_numpy()
            bad = inversions(v) - (sum(inversions(v[other == o]) for o in np.unique(other)) if axis == "q" else 0)
            return pd.DataFrame({"bad": [bad]})

        return count

    same_p = cells.groupBy("bp").applyInPandas(inside("p", "q"), "bad long").agg(F.sum("bad")).first()[0]
    same_q = cells.groupBy("bq").applyInPandas(inside("q", "p"), "bad long").agg(F.sum("bad")).first()[0]
    blocks = -(-n // block)
    grid = np.zeros((blocks + 1, blocks + 1), np.int64)
    for r in cells.groupBy("bp", "bq").agg(F.count("*").alias("n")).collect():
        grid[r["bp"], r["bq"]] = r["n"]
    behind = grid[::-1].cumsum(0)[::-1].cumsum(1)  # users from a block on in p and up to a block in q
    apart = int((grid[:-1, 1:] * behind[1:, :-1]).sum())
    return n, int(same_p + same_q + apart)


def kendall_large(predicted: DataFrame, truth: DataFrame, block: int = 200_000) -> float | None:
    """tau-a without ties."""
    ranked = global_rank(predicted.select("user_id", "score"), ["score", "user_id"], "p").join(global_rank(truth.select("user_id", "score"), ["score", "user_id"], "q").select("user_id", "q"), "user_id")
    n, inverted = inverted_pairs(ranked.select("p", "q"), block)
    return 1 - 4 * inverted / (n * (n - 1)) if n > 1 else None


def mean_correctness(responses: DataFrame, key: DataFrame) -> DataFrame:
    """One row: the share of correct answers."""
    joined = responses.join(key.withColumnRenamed("option_id", "right_option"), "item_id")
    return joined.agg(F.avg((F.col("option_id") == F.col("right_option")).cast("double")).alias("correctness"))


def eigvec_variance(scores: DataFrame, truth_order: DataFrame) -> DataFrame:
    """One row: variance of the unit difference vector with users in their true order.

    truth_order: user_id, pos."""
    d = linalg.to_diffs(scores, truth_order)
    unit = d.crossJoin(F.broadcast(d.agg(F.sqrt(F.sum(F.col("diff") * F.col("diff"))).alias("norm")))).select((F.col("diff") / F.col("norm")).alias("x"))
    return unit.agg(F.var_pop("x").alias("variance"))


def displacement(runs: list[DataFrame]) -> DataFrame:
    """One row: mean over users and pairs of runs of the difference of ranks, over the users' number."""
    tagged = reduce(DataFrame.unionByName, [r.select("user_id", F.col("rank").cast("double").alias("rank"), F.lit(i).alias("run")) for i, r in enumerate(runs)])
    a, b = tagged.alias("a"), tagged.alias("b")
    pairs = a.join(b, (F.col("a.user_id") == F.col("b.user_id")) & (F.col("a.run") < F.col("b.run"))).select(F.col("a.user_id").alias("user_id"), F.abs(F.col("a.rank") - F.col("b.rank")).alias("d"))
    return pairs.groupBy("user_id").agg(F.avg("d").alias("d")).agg((F.avg("d") / F.count("*")).alias("displacement"))


def auc(scores: DataFrame, labels: DataFrame) -> DataFrame:
    """One row: chance that a positive outranks a negative, by rank sums; labels: user_id, label 0/1."""
    ranked = average_ranks(scores.join(labels.select("user_id"), "user_id", "left_semi"), "r").join(labels, "user_id")
    n = ranked.agg(F.sum(F.when(F.col("label") == 1, F.col("r"))).alias("s"), F.sum((F.col("label") == 1).cast("long")).alias("p"), F.sum((F.col("label") == 0).cast("long")).alias("q"))
    return n.select(((F.col("s") - F.col("p") * (F.col("p") + 1) / 2.0) / (F.col("p") * F.col("q"))).alias("auc"))


def mean_over(results: DataFrame) -> DataFrame:
    """method, metric: mean and spread over data sets and repeats."""
    return results.groupBy("method", "metric").agg(F.avg("value").alias("mean"), F.stddev_samp("value").alias("spread"), F.count("*").alias("n"))


def wins(results: DataFrame) -> DataFrame:
    """How many data sets each method is best on."""
    best = Window.partitionBy("dataset").orderBy(F.desc("value"), "method")
    return results.withColumn("r", F.row_number().over(best)).where("r = 1").groupBy("method").agg(F.count("*").alias("wins"))
