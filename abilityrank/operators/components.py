"""Connected components of the graph of users and options."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import OPTION
from ..plans.storage import written


def components(responses: DataFrame) -> DataFrame:
    """user_id, component (its smallest user): each round takes the smallest label over options,
    then jumps along labels, so rounds grow with the logarithm of distances."""
    rows = responses.select("user_id", *OPTION)
    labels = written(rows.groupBy("user_id").agg(F.min("user_id").alias("component")), "labels")
    while True:
        small = rows.join(labels, "user_id").groupBy(*OPTION).agg(F.min("component").alias("c"))
        near = rows.join(small, OPTION).groupBy("user_id").agg(F.min("c").alias("c"))
        joined = labels.join(near, "user_id").select("user_id", F.col("component").alias("old"), F.least("component", "c").alias("c"))
        # a user's old label hooks to the smallest label that any of its users found
        hook = joined.groupBy("old").agg(F.min("c").alias("to")).withColumnRenamed("old", "from")
        moved = joined.join(hook, joined.c == F.col("from"), "left").select("user_id", "old", F.least(F.col("c"), F.coalesce("to", "c")).alias("component"))
        moved = written(moved, "labels")
        labels = moved.select("user_id", "component")
        if not moved.where("component <> old").limit(1).count():
            return labels


def require_connected(responses: DataFrame, on_fail: str = "raise") -> DataFrame:
    """The answers if they connect all users; else an error, the largest component, or all answers
    with their component (per_component)."""
    found = written(components(responses), "components")
    sizes = found.groupBy("component").agg(F.count("*").alias("n"))
    if sizes.limit(2).count() < 2 and on_fail != "per_component":
        return responses
    if on_fail == "raise":
        raise ValueError("users fall into several components: no order between them; see on_fail")
    if on_fail == "largest":
        keep = sizes.orderBy(F.desc("n"), "component").limit(1).select("component")
        return responses.join(found.join(keep, "component").select("user_id"), "user_id", "left_semi")
    if on_fail == "per_component":
        return responses.join(found, "user_id")
    raise ValueError("on_fail: raise, largest or per_component")


def teleport(scores: DataFrame, share: float = 0.15) -> DataFrame:
    """Scores mixed with their mean: one round of a jump to any user, for graphs that fall apart."""
    mean = scores.agg(F.avg("score").alias("mean"))
    return scores.crossJoin(F.broadcast(mean)).select("user_id", ((1 - share) * F.col("score") + share * F.col("mean")).alias("score"))
