"""Connected components of a graph given as edges, by hooking and contraction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.io import remove, written


def components(edges: DataFrame, nodes: DataFrame | None = None) -> DataFrame:
    """(node, component): component is the smallest node reachable over edges (a, b), any number of them.

    Every round hooks each node to its smallest neighbour if that is smaller, follows the hooks to their ends, and goes on with
    the edges between different ends.  A node with a smaller neighbour goes, so at least half of those left do, whatever
    the order of their names; long chains cost rounds in the logarithm of their length.  Each step is written to the shared folder.
    Edges are read once.  nodes: further nodes (node), without edges perhaps.  Null ends and loops are ignored."""
    spark = edges.sparkSession
    ends = edges.where("a is not null and b is not null and a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
    e, at_e = written(ends.distinct(), "edges")
    labels, at_labels = written(e.select(F.explode(F.array("a", "b")).alias("node")).distinct().select("node", F.col("node").alias("component")), "labels")
    while not e.isEmpty():
        ways = e.select(F.explode(F.array(F.struct(F.col("a").alias("x"), F.col("b").alias("y")), F.struct(F.col("b").alias("x"), F.col("a").alias("y")))).alias("w"))
        hooks, at_hooks = written(ways.groupBy("w.x").agg(F.min("w.y").alias("y")).select(F.col("x").alias("from"), F.least("x", "y").alias("to")), "hooks")
        while True:
            far = hooks.select(F.col("from").alias("via"), F.col("to").alias("end"))
            after, at_after = written(hooks.join(far, hooks["to"] == far["via"]).select("from", F.col("end").alias("to"), (F.col("end") != F.col("to")).alias("moved")), "hooks")
            remove(spark, at_hooks)
            hooks, at_hooks = after.select("from", "to"), at_after
            if after.where("moved").isEmpty():
                break
        moved, at_moved = written(labels.join(hooks, labels["component"] == hooks["from"], "left").select("node", F.coalesce("to", "component").alias("component")), "labels")
        side = lambda c: hooks.select(F.col("from").alias(c), F.col("to").alias(f"{c}_to"))  # noqa: E731, B023
        left = e.join(side("a"), "a").join(side("b"), "b").where("a_to <> b_to")
        rest, at_rest = written(left.select(F.least("a_to", "b_to").alias("a"), F.greatest("a_to", "b_to").alias("b")).distinct(), "edges")
        for path in (at_labels, at_e, at_hooks):
            remove(spark, path)
        labels, at_labels, e, at_e = moved, at_moved, rest, at_rest
    if nodes is None:
        return labels
    alone = nodes.select("node").distinct().join(labels.select("node"), "node", "left_anti")
    return labels.unionByName(alone.select("node", F.col("node").alias("component")))
