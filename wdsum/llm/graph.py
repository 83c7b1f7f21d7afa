"""Connected components by contraction, every step a join of tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .stored import stored


def components(edges: DataFrame, rounds: int = 100) -> DataFrame:
    """(node, root) of every node of ``edges`` (a long, b long); root is the component's own.

    Each round every node joins what its smallest neighbour joins, if that is
    smaller, and edges are drawn again between what nodes have joined; the number
    of rounds is about the logarithm of a component's diameter. Loops and repeats of
    edges don't matter; null ends are dropped. Nothing is collected.
    """
    both = lambda e: e.unionByName(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
    # stored first: both directions must be of the same edges, and whatever makes them may not be the same twice
    given = stored(edges.select("a", "b").where("a is not null and b is not null"))
    rows = 2 * given.count()
    now = stored(both(given).distinct(), rows)
    known: DataFrame | None = None
    for _ in range(rounds):
        # a loop keeps a node that has nothing else
        near = stored(now.groupBy("a").agg(F.least(F.col("a"), F.min("b")).alias("to")), rows)
        joined = stored(near.join(near.select(F.col("a").alias("to"), F.col("to").alias("next")), "to").select("a", F.col("next").alias("to")), rows)
        known = joined.select(F.col("a").alias("node"), F.col("to").alias("root")) if known is None else known.join(joined.withColumnRenamed("a", "root"), "root", "left").select("node", F.coalesce("to", "root").alias("root"))
        known = stored(known, rows)
        step = now.where("a < b").join(joined, "a").select(F.col("to").alias("x"), "b").join(joined.select(F.col("a").alias("b"), F.col("to").alias("y")), "b")
        now = stored(both(step.where("x != y").select(F.col("x").alias("a"), F.col("y").alias("b"))).distinct(), rows)
        if not now.take(1):
            return known
    raise RuntimeError("components did not settle")
