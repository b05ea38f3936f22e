"""Methods of the earlier suites that the three main ones build on: distances, reachability, ranks, coarsening."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.graphs import PartitionedGraph
from ..storage import spill
from .clustering import assign


def _sources(g: PartitionedGraph, vids: list[int]) -> DataFrame:
    spark = g.vertices.sparkSession
    return spark.createDataFrame(list(enumerate(vids)), "centre_rank int, vid bigint").join(g.vertices.select("vid"), "vid", "left_semi")


def sssp(g: PartitionedGraph, source: int, unit: str = "vertex") -> DataFrame:
    """(vid, dist): hops from ``source`` to each vertex it reaches."""
    return assign(g, _sources(g, [source]), unit)[0].select("vid", F.col("dist").cast("bigint").alias("dist"))


def reachable(g: PartitionedGraph, sources: list[int]) -> DataFrame:
    """(vid, reached) of every vertex."""
    got = assign(g, _sources(g, sources), "vertex")[0].select("vid", F.lit(True).alias("hit"))
    return g.vertices.select("vid").join(got, "vid", "left").select("vid", F.coalesce("hit", F.lit(False)).alias("reached"))


#: Parts of a rank of 1; whole numbers add up alike in any order.
UNIT = 10**12


def pagerank(g: PartitionedGraph, rounds: int = 5, damping: int = 85) -> DataFrame:
    """(vid, score): ranks in parts of UNIT, after ``rounds`` rounds; a vertex gives floor(rank / degree) to each neighbour
    and one without neighbours keeps the base share."""
    n = g.vertices.count()
    half = spill(g.half_edges().select("u", "v"))
    deg = half.groupBy("u").agg(F.count("*").alias("d"))
    base = UNIT * (100 - damping) // (100 * n)
    rank = g.vertices.select("vid", F.lit(UNIT // n).cast("bigint").alias("score"))
    for _ in range(rounds):
        share = rank.join(deg, rank["vid"] == deg["u"]).select("u", F.expr("score div d").alias("part"))
        got = half.join(share, "u").groupBy(F.col("v").alias("vid")).agg(F.sum("part").alias("got"))
        rank = spill(g.vertices.select("vid").join(got, "vid", "left").select("vid", (F.expr(f"coalesce(got, 0) * {damping} div 100") + base).alias("score")))
    return rank


def subgraph_rank(g: PartitionedGraph, rounds: int = 5) -> DataFrame:
    """(sg, score): rank of a whole subgraph, the sum over its vertices."""
    return pagerank(g, rounds).join(g.vertices.select("vid", "sg"), "vid").groupBy("sg").agg(F.sum("score").alias("score"))


def betweenness(g: PartitionedGraph, sources: list[int], max_steps: int = 1000) -> DataFrame:
    """(vid, score): for each vertex the share of shortest paths from ``sources`` that pass through it, summed over targets.

    Forward: levels with path counts for all sources at once. Backward: each level hands its dependency to the one before.
    """
    half = spill(g.half_edges().select("u", "v"))
    level = spill(_sources(g, sources).select(F.col("vid").alias("s"), "vid", F.lit(0).alias("dist"), F.lit(1.0).alias("paths")))
    seen, levels = level, [level]
    for step in range(1, max_steps + 1):
        nxt = level.join(half, F.col("vid") == F.col("u")).groupBy("s", F.col("v").alias("vid")).agg(F.sum("paths").alias("paths"))
        level = spill(nxt.join(seen.select("s", "vid"), ["s", "vid"], "left_anti").select("s", "vid", F.lit(step).alias("dist"), "paths"))
        if level.isEmpty():
            break
        levels.append(level)
        seen = seen.unionByName(level)
    owed = levels[-1].select("s", "vid", "paths", F.lit(0.0).alias("owed"))
    total = [owed]
    for before in reversed(levels[:-1]):
        up = owed.select("s", F.col("vid").alias("v"), ((1 + F.col("owed")) / F.col("paths")).alias("each"))
        got = half.join(up, "v").groupBy("s", F.col("u").alias("vid")).agg(F.sum("each").alias("each"))
        owed = spill(before.join(got, ["s", "vid"], "left").select("s", "vid", "paths", (F.col("paths") * F.coalesce("each", F.lit(0.0))).alias("owed")))
        total.append(owed)
    every = total[0]
    for t in total[1:]:
        every = every.unionByName(t)
    return every.where("s <> vid").groupBy("vid").agg(F.round(F.sum("owed"), 6).alias("score"))


def coarsen(g: PartitionedGraph) -> PartitionedGraph:
    """Each subgraph becomes one vertex; of the cut edges between two the least weight stays."""
    e = g.owned_edges().where("src_sg <> dst_sg")
    edges = e.groupBy(F.least("src_sg", "dst_sg").alias("src"), F.greatest("src_sg", "dst_sg").alias("dst")).agg(F.min("weight").alias("weight"))
    return PartitionedGraph(g.vertices.select(F.col("sg").alias("vid"), "sg").distinct(), edges)
