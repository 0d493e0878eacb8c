"""Which end of an order is the able one: able users agree more."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.draws import entropy_of
from ..model import OPTION
from .metrics import spearman
from .rank import rank_users


def slice_entropy(responses: DataFrame, ranking: DataFrame, share: float = 0.1) -> DataFrame:
    """side (low: smallest ranks, high), entropy (mean over the items answered there, in nats), items.

    A slice holds ceil(users * share) users, at least one."""
    m = ranking.agg(F.count("*").alias("m"), F.greatest(F.lit(1), F.ceil(F.count("*") * F.lit(share))).alias("size"))
    sided = ranking.select("user_id", "rank").crossJoin(F.broadcast(m))
    low = sided.where("rank <= size").select("user_id", F.lit("low").alias("side"))
    high = sided.where("rank > m - size").select("user_id", F.lit("high").alias("side"))
    counts = responses.join(low.union(high), "user_id").groupBy("side", *OPTION).agg(F.count("*").alias("n"))
    totals = counts.groupBy("side", "item_id").agg(F.sum("n").alias("total"))
    per_item = counts.join(totals, ["side", "item_id"]).groupBy("side", "item_id").agg(entropy_of(F.col("n") / F.col("total")).alias("h"))
    return per_item.groupBy("side").agg(F.avg("h").alias("entropy"), F.count("*").alias("n_items"))


def orient_by_entropy(responses: DataFrame, scores: DataFrame, share: float = 0.1, digits: int = 9) -> tuple[DataFrame, str]:
    """(scores with the able end high, kept | reversed | undetermined).  Slices that tie are widened
    twice over, up to half of the users."""
    ranking = rank_users(scores, digits)  # rank 1: highest score
    while True:
        h = {r["side"]: r["entropy"] for r in slice_entropy(responses, ranking, share).collect()}
        top, bottom = h.get("low"), h.get("high")
        if top is not None and bottom is not None and abs(top - bottom) > 1e-12:
            kept = top < bottom
            return (scores if kept else scores.withColumn("score", -F.col("score"))), "kept" if kept else "reversed"
        if share >= 0.5:
            return scores, "undetermined"
        share = min(0.5, share * 2)


def orient_by_truth(scores: DataFrame, truth: DataFrame) -> DataFrame:
    """For evaluation only: the direction that agrees with the true order."""
    return scores if (spearman(scores, truth) or 0.0) >= 0 else scores.withColumn("score", -F.col("score"))
