"""Connected components of an undirected edge list, as DataFrame rounds."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize, release


def components(edges: DataFrame) -> DataFrame:
    """(node, comp) of every node of edges (a, b); comp is the smallest node of its component.

    Each round takes the smallest label among neighbours and then the label of that
    label, so long chains shrink by doubling. State is written after every round.
    """
    both = materialize(edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).where("a <> b").distinct(), "cc-edges")
    state = materialize(both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("node"), F.least("a", "m").alias("comp")), "cc-state")
    while True:
        near = both.join(state.select(F.col("node").alias("b"), "comp"), "b").groupBy("a").agg(F.min("comp").alias("m"))
        lower = state.join(near, state.node == near.a).select("node", "comp", F.least("comp", "m").alias("next"))
        lower = materialize(lower, "cc-lower")
        jump = lower.select(F.col("node").alias("next"), F.col("next").alias("far"))
        done = materialize(lower.join(jump, "next").select("node", F.col("far").alias("comp"), (F.col("far") != F.col("comp")).alias("moved")), "cc-state")
        moved = not done.where("moved").isEmpty()
        release(state, lower)
        state = done.select("node", "comp")
        state._scratch = done._scratch
        if not moved:
            release(both)
            return state
