"""Connected components of links in DataFrames: least labels with pointer jumping, each round in files."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import saved


def components(links: DataFrame, name: str = "components") -> DataFrame:
    """(node, component) for nodes that have a link; a component is named by its least node.

    ``links`` has columns x and y.  Each round gives a node the least label among its own and its
    neighbours', then follows the label's own label once, so that chains shrink by halves.  Rounds end when
    no label moves.  Null ends and self links are left out; repeated links do no harm.
    """
    pairs = links.where("x <> y").select("x", "y")
    both = saved(pairs.union(pairs.select("y", "x")).distinct(), f"{name}-links")
    labels = saved(both.groupBy(F.col("x").alias("node")).agg(F.least(F.col("node"), F.min("y")).alias("component")), name)
    while True:
        near = both.join(labels, both.y == labels.node).groupBy(F.col("x").alias("node")).agg(F.min("component").alias("near"))
        stepped = labels.join(near, "node").select("node", F.least("component", "near").alias("component"), F.col("component").alias("was"))
        up = labels.select(F.col("node").alias("component"), F.col("component").alias("root"))
        moved = saved(stepped.join(up, "component", "left").select("node", F.least("component", F.coalesce("root", "component")).alias("component"), "was"), name)
        labels = moved.select("node", "component")
        if moved.where("component <> was").isEmpty():
            return labels
