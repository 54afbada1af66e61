"""Connected components over an edge table, by minimum labels and pointer jumping."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stationlink.plans.workspace import materialize


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, root) for every node of ``edges`` (columns src, dst); root is the smallest node it reaches.

    Null ends are ignored; loops give a component of their own. Each round takes the smallest label among a node's
    neighbours (a pre-aggregated shuffle) and then follows that label once more, so chains shrink geometrically. The
    label table is written out each round; nothing but one number per round reaches the driver.
    """
    pairs = edges.select("src", "dst").where("src is not null and dst is not null")
    both = pairs.unionByName(pairs.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()
    both = materialize(both, "edges")
    labels = materialize(both.groupBy(F.col("src").alias("node")).agg(F.least("src", F.min("dst")).alias("root")), "labels")
    for _ in range(max_rounds):
        seen = both.join(labels, both.dst == labels.node).groupBy("src").agg(F.min("root").alias("near"))
        hooked = labels.join(seen, labels.node == seen.src).select("node", F.col("root").alias("was"), F.least("root", "near").alias("root"))
        up = labels.select(F.col("node").alias("via"), F.col("root").alias("above"))
        moved = hooked.join(up, hooked.root == up.via).select("node", "was", F.least("root", "above").alias("root"))
        step = materialize(moved, "labels")
        changed = step.where("root < was").limit(1).count()
        labels = step.select("node", "root")
        if not changed:
            return labels
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")
