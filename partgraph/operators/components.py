"""Connected components by least-label hooking and pointer jumping."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import spill


def connected_components(edges: DataFrame, max_rounds: int = 100) -> DataFrame:
    """(vid, comp): for each end of an edge (src, dst) the least vertex id that it can reach.

    A round lowers every label to the least among its neighbours and then follows the label's own label, so long chains
    shrink by halves. Loops and repeated edges are harmless; no edges give no rows; null ends are left out.
    """
    ends = edges.select(F.col("src").cast("bigint").alias("u"), F.col("dst").cast("bigint").alias("v")).where("u is not null and v is not null")
    both = spill(ends.union(ends.select("v", "u")).distinct())
    labels = spill(both.groupBy(F.col("u").alias("vid")).agg(F.least("vid", F.min("v")).alias("comp")))
    for _ in range(max_rounds):
        near = both.join(labels, F.col("v") == F.col("vid")).groupBy("u").agg(F.min("comp").alias("low"))
        hooked = labels.join(near, F.col("vid") == F.col("u")).select("vid", "comp", F.least("comp", "low").alias("low"))
        root = labels.select(F.col("vid").alias("low"), F.col("comp").alias("jump"))
        jumped = spill(hooked.join(root, "low").select("vid", "comp", F.least("low", "jump").alias("new")))
        labels = jumped.select("vid", F.col("new").alias("comp"))
        if jumped.where("new < comp").isEmpty():
            return labels
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")
