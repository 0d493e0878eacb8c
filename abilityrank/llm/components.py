"""Connected components of an edge table by repeated contraction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import materialise


def components(edges: DataFrame) -> DataFrame:
    """edges: a, b (long).  Returns node, root for every node of an edge; the root is the smallest
    node of its component.

    In each round every node hooks to its smallest neighbour or itself and edges are carried over to
    the hooked nodes; at least half of the nodes with edges go, so rounds are logarithmic.
    """
    edges = materialise(edges.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "edges")
    where = materialise(edges.select(F.col("a").alias("node")).union(edges.select("b")).distinct().withColumn("root", F.col("node")), "roots")
    while edges.limit(1).count():
        hook = materialise(edges.select(F.col("b").alias("at"), F.col("a").alias("to")).union(edges.select("a", "a")).groupBy("at").agg(F.min("to").alias("to")), "hooks")
        where = materialise(where.join(hook, where.root == hook.at, "left").select("node", F.coalesce("to", "root").alias("root")), "roots")
        one = edges.join(hook, edges.a == hook.at).select(F.col("to").alias("a"), "b")
        two = one.join(hook, one.b == hook.at).select("a", F.col("to").alias("b")).where("a <> b")
        edges = materialise(two.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "edges")
    return where
