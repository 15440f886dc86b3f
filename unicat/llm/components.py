"""Connected components of an edge table by hooking roots and pointer jumping, until nothing moves.

In a round each node, and the node that its label names, takes the lowest label among the node's neighbours; then labels
jump to their own labels. Whole trees merge that way: a shuffled chain of 5,000 nodes takes about 12 rounds, one of
100,000 about 15. Labels only fall, so the rounds end without a bound. Each round is a few joins over tables in the shared folder. Labels of the few nodes with very many edges are broadcast
(at most HEAVY_SHARE rows), so that no task gets all edges of one node.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialise, split_heavy


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """node, label (the smallest node of its component) for every node that an edge touches. Edges may repeat or be loops."""
    both = edges.select(F.col(a).alias("u"), F.col(b).alias("v")).unionByName(edges.select(F.col(b).alias("u"), F.col(a).alias("v")))
    both = materialise(both.where("u <> v").distinct(), "edges")
    labels = materialise(both.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("low"), F.count(F.lit(1)).alias("degree")).select("node", F.least("node", "low").alias("label"), "degree"), "labels")
    heavy, _ = split_heavy(labels, "degree") if labels.limit(1).count() else (None, labels)
    heavy_nodes = None if heavy is None else materialise(heavy.select("node"), "heavy-nodes")
    while True:
        low = _lowest(both, labels, heavy_nodes)
        seen = materialise(labels.join(low, "node", "left").select("node", "label", F.least("label", F.coalesce("low", "label")).alias("low"), "degree"), "seen")
        # What any node of a tree sees, the node that the tree's label names sees too.
        roots = seen.where("low < label").groupBy(F.col("label").alias("node")).agg(F.min("low").alias("hook"))
        hooked = seen.join(roots, "node", "left").select("node", F.least("low", F.coalesce("hook", "low")).alias("label"), "degree", F.col("label").alias("was"))
        hooked = materialise(hooked, "hooked")
        if not hooked.where("label <> was").limit(1).count():
            return hooked.select("node", "label")
        up = hooked.select(F.col("node").alias("label"), F.col("label").alias("above"))
        # A label is a node of the same component; jumping to its own label halves the way to the root.
        jumped = hooked.join(up, "label", "left").select("node", F.least("label", F.coalesce("above", "label")).alias("label"), "degree")
        labels = materialise(jumped, "labels")


def _lowest(both: DataFrame, labels: DataFrame, heavy_nodes: DataFrame | None) -> DataFrame:
    """The lowest label among each node's neighbours."""
    near = labels.select(F.col("node").alias("v"), "label")
    if heavy_nodes is None:
        rows = both.join(near, "v")
    else:
        hot = heavy_nodes.select(F.col("node").alias("v"))
        rows = both.join(F.broadcast(hot), "v", "left_anti").join(near, "v").unionByName(both.join(F.broadcast(near.join(F.broadcast(hot), "v")), "v"))
    return rows.groupBy(F.col("u").alias("node")).agg(F.min("label").alias("low"))
