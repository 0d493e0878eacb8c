"""Global positions and rankings without single-partition windows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..plans.storage import written


def global_rank(df: DataFrame, order: list[str | Column], name: str = "rank", partitions: int | None = None) -> DataFrame:
    """df with positions 1, 2, .. in the given order: ranges are sorted apart and offset by the
    sizes of the ranges before them (one row a range)."""
    columns = [F.col(c) if isinstance(c, str) else c for c in order]
    ranged = df.repartitionByRange(partitions, *columns) if partitions else df.repartitionByRange(*columns)
    # the range's number is written with the rows: a recomputed range split could differ
    placed = written(ranged.withColumn("_range", F.spark_partition_id()), "ranges")
    sizes = placed.groupBy("_range").agg(F.count("*").alias("_size"))
    before = sizes.select("_range", (F.sum("_size").over(Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1))).alias("_before"))  # one row a range
    own = Window.partitionBy("_range").orderBy(*columns)
    return placed.withColumn(name, F.row_number().over(own).cast("long")).join(F.broadcast(before), "_range").withColumn(name, F.col(name) + F.coalesce("_before", F.lit(0)).cast("long")).drop("_range", "_before")


def rank_users(scores: DataFrame, digits: int = 9, ties: str = "id", descending: bool = True) -> DataFrame:
    """user_id, score, rank.  Scores are rounded first, as exact ties differ in their last bits.

    ties: id (by user_id, all ranks differ), min (equal scores share the smallest) or average.
    """
    rounded = scores.select("user_id", (F.round("score", digits) + F.lit(0.0)).alias("score"))
    key = F.desc("score") if descending else F.asc("score")
    ranked = global_rank(rounded, [key, F.col("user_id")])
    if ties == "id":
        return ranked
    same = ranked.groupBy("score").agg((F.min("rank") if ties == "min" else F.avg("rank")).alias("rank"))
    return ranked.drop("rank").join(same, "score").select("user_id", "score", "rank")
