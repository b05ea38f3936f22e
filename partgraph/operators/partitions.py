"""Partitions of a graph into subgraphs, their meta-graph and their shape."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.graphs import PartitionedGraph
from ..storage import spill
from .components import connected_components


def hash_part(vid, parts: int):
    """Part of a vertex id by the first eight digits of its MD5, the same in any engine."""
    return F.pmod(F.conv(F.substring(F.md5(vid.cast("string")), 1, 8), 16, 10).cast("bigint"), F.lit(parts))


def partition_hash(g: PartitionedGraph, parts: int) -> PartitionedGraph:
    return g.with_partition(hash_part(F.col("vid"), parts))


def partition_range(g: PartitionedGraph, parts: int) -> PartitionedGraph:
    """Equal ranges of the id space."""
    top = g.vertices.agg(F.max("vid") + 1).first()[0] or 1
    return g.with_partition(F.expr(f"vid * {parts} div {top}"))


def partition_single(g: PartitionedGraph) -> PartitionedGraph:
    return g.with_partition(F.lit(0))


def partition_singletons(g: PartitionedGraph) -> PartitionedGraph:
    return g.with_partition(F.col("vid"))


def _with_labels(g: PartitionedGraph, labels: DataFrame, label: str, otherwise) -> PartitionedGraph:
    met = g.vertices.select("vid", "sg").join(labels.select("vid", F.col(label).cast("bigint").alias("new")), "vid", "left")
    return PartitionedGraph(met.select("vid", F.coalesce("new", otherwise).cast("bigint").alias("sg")), g.edges)


def partition_components(g: PartitionedGraph) -> PartitionedGraph:
    """One subgraph for each connected component: no edge is cut."""
    return _with_labels(g, connected_components(g.edges), "comp", F.col("vid"))


def assign_subgraphs(g: PartitionedGraph, unit: str = "component") -> PartitionedGraph:
    """``partition``: a partition is one subgraph. ``component``: each connected piece of a partition is one."""
    if unit == "partition":
        return g
    inner = g.owned_edges().where("src_sg = dst_sg").select("src", "dst")
    return _with_labels(g, connected_components(inner), "comp", F.col("vid"))


def partition_kway(g: PartitionedGraph, parts: int, seed: int = 7) -> PartitionedGraph:
    """Breadth-first regions round random centres; vertices that no centre reaches share one more part."""
    from .clustering import assign, draw_centres

    return _with_labels(g, assign(g, draw_centres(g, parts, seed), "vertex")[0], "centre_rank", F.lit(parts))


def partition_lp(g: PartitionedGraph, parts: int, rounds: int = 6, slack: float = 0.1) -> PartitionedGraph:
    """Label propagation under a size cap: stands in for a multilevel minimum-cut partitioner.

    Starts from equal id ranges. In a round, vertices of one half (by a hash of id and round, so that neighbours do not
    swap labels) ask for the label that most of their neighbours have, if it has more than their own; a label takes the
    askers with the largest gain, up to its free room. No label grows beyond (1 + slack) n / parts.
    """
    g = PartitionedGraph(g.vertices.select("vid", "sg"), g.edges)
    half = spill(g.half_edges().select("u", "v"))
    start = partition_range(g, parts).vertices
    labels = spill(start.select("vid", F.col("sg").alias("label")))
    cap = int((1 + slack) * labels.count() / parts) + 1
    for r in range(rounds):
        seen = half.join(labels.select(F.col("vid").alias("v"), F.col("label").alias("to")), "v").groupBy("u", "to").agg(F.count("*").alias("n"))
        mine = labels.where(hash_part(F.concat_ws(":", F.lit(r), "vid"), 2) == 0)
        had = seen.select(F.col("u").alias("vid"), F.col("to").alias("label"), F.col("n").alias("own"))
        best = seen.groupBy("u").agg(F.max(F.struct("n", (-F.col("to")).alias("least"))).alias("x")).select(F.col("u").alias("vid"), F.col("x.n").alias("n"), (-F.col("x.least")).alias("to"))
        asks = mine.join(best, "vid").join(had, ["vid", "label"], "left").withColumn("gain", F.col("n") - F.coalesce("own", F.lit(0))).where("gain > 0 and to <> label")
        size = labels.groupBy(F.col("label").alias("to")).agg(F.count("*").alias("size"))
        w = Window.partitionBy("to").orderBy(F.desc("gain"), "vid")
        taken = asks.withColumn("turn", F.row_number().over(w)).join(size, "to", "left").where(F.col("turn") + F.coalesce("size", F.lit(0)) <= cap).select("vid", "to")
        labels = spill(labels.join(taken, "vid", "left").select("vid", F.coalesce("to", "label").alias("label")), labels)
    return _with_labels(g, labels, "label", F.lit(0))


def meta_graph(g: PartitionedGraph) -> DataFrame:
    """(src_sg, dst_sg, cut_edges), src_sg < dst_sg: subgraphs that share cut edges."""
    e = g.owned_edges().where("src_sg <> dst_sg")
    return e.groupBy(F.least("src_sg", "dst_sg").alias("src_sg"), F.greatest("src_sg", "dst_sg").alias("dst_sg")).agg(F.count("*").alias("cut_edges"))


def meta_distances(g: PartitionedGraph, max_steps: int = 1000) -> DataFrame:
    """(a, b, hops): least number of steps between subgraphs that reach each other; one row for each such pair."""
    m = spill(meta_graph(g).select(F.col("src_sg").alias("u"), F.col("dst_sg").alias("v")))
    half = m.union(m.select("v", "u"))
    reach = spill(g.vertices.select(F.col("sg").alias("a"), F.col("sg").alias("b")).distinct().withColumn("hops", F.lit(0)))
    front = reach
    for step in range(1, max_steps + 1):
        new = front.join(half, F.col("b") == F.col("u")).select("a", F.col("v").alias("b")).distinct().join(reach.select("a", "b"), ["a", "b"], "left_anti")
        front = spill(new.withColumn("hops", F.lit(step)))
        if front.isEmpty():
            return reach
        reach = spill(reach.unionByName(front), reach)
    raise RuntimeError(f"meta-graph not crossed in {max_steps} steps")


def meta_diameter(g: PartitionedGraph) -> DataFrame:
    """(subgraphs, meta_edges, meta_diameter): the largest finite distance."""
    return meta_distances(g).agg(F.countDistinct("a").alias("subgraphs"), F.count_if((F.col("hops") == 1) & (F.col("a") < F.col("b"))).alias("meta_edges"), F.max("hops").cast("bigint").alias("meta_diameter"))


def partition_stats(g: PartitionedGraph) -> DataFrame:
    """(sg, vertices, inner_edges, cut_edges) of each subgraph."""
    e = g.owned_edges()
    sides = e.select(F.col("src_sg").alias("sg"), (F.col("src_sg") != F.col("dst_sg")).alias("cut"))
    far = e.where("src_sg <> dst_sg").select(F.col("dst_sg").alias("sg"), F.lit(True).alias("cut"))
    counts = sides.unionByName(far).groupBy("sg").agg(F.count_if(~F.col("cut")).alias("inner_edges"), F.count_if("cut").alias("cut_edges"))
    n = g.vertices.groupBy("sg").agg(F.count("*").alias("vertices"))
    return n.join(counts, "sg", "left").select("sg", "vertices", F.coalesce("inner_edges", F.lit(0)).alias("inner_edges"), F.coalesce("cut_edges", F.lit(0)).alias("cut_edges"))


def graph_shape(g: PartitionedGraph) -> DataFrame:
    """One row of measures: n, m, arrows (2m), d_max, subgraphs p, l_max (vertices), r_max (cut edges), cut, and
    ``excess`` = percent by which the largest subgraph exceeds n / p."""
    stats = partition_stats(g).agg(F.sum("vertices").alias("n"), F.count("*").alias("p"), F.max("vertices").alias("l_max"), F.max("cut_edges").alias("r_max"), (F.sum("cut_edges") / 2).cast("bigint").alias("cut"), F.sum("inner_edges").alias("inner"))
    deg = g.edges.select(F.explode(F.array("src", "dst")).alias("vid")).groupBy("vid").agg(F.count("*").alias("d")).agg(F.coalesce(F.max("d"), F.lit(0)).alias("d_max"))
    m = F.col("cut") + F.col("inner")
    return stats.crossJoin(deg).select("n", m.alias("m"), (2 * m).alias("arrows"), "d_max", "p", "l_max", "r_max", "cut", F.expr("(l_max * p * 100) div n - 100").alias("excess"))
