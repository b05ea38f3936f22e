"""k-way clustering: random centres, multi-source breadth-first labels, edge cut, redraw until the cut is small enough."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.graphs import PartitionedGraph
from ..storage import forget, spill
from .bsp import MessageLog, Phase
from .components import connected_components


def _key(seed: int, round_: int, *more: str):
    return F.md5(F.concat_ws(":", F.lit(seed), F.lit(round_), *map(F.lit, more), "vid"))


def _ranked(best: DataFrame) -> DataFrame:
    return best.withColumn("centre_rank", (F.row_number().over(Window.orderBy("key", "vid")) - 1).cast("int")).select("centre_rank", "vid")


def draw_centres(g: PartitionedGraph, k: int, seed: int = 7, round_: int = 0, sampling: str = "reservoir") -> DataFrame:
    """(centre_rank, vid): the k least keys; Spark takes k in every task before it merges.

    ``reservoir`` gives every vertex a key, so that all are as likely. ``per_subgraph`` lets each subgraph pick k of its
    vertices first and keys only these: vertices of small subgraphs are likelier.
    """
    v = g.vertices.select("vid", "sg")
    if sampling == "per_subgraph":
        w = Window.partitionBy("sg").orderBy(_key(seed, round_, "pick"), "vid")
        v = v.withColumn("turn", F.row_number().over(w)).where(F.col("turn") <= k)
    elif sampling != "reservoir":
        raise ValueError(sampling)
    return _ranked(v.select("vid", _key(seed, round_).alias("key")).orderBy("key", "vid").limit(k))


def draw_exchange(g: PartitionedGraph, k: int, seed: int = 7, round_: int = 0) -> DataFrame:
    """(to_sg, received, centre_rank, vid): the draw by messages. Each subgraph sends its k least keys to every subgraph,
    and every subgraph picks the same k of what it received."""
    w = Window.partitionBy("sg").orderBy("key", "vid")
    mine = g.vertices.select("sg", "vid", _key(seed, round_).alias("key")).withColumn("turn", F.row_number().over(w)).where(F.col("turn") <= k)
    received = mine.select("vid", "key").crossJoin(g.vertices.select(F.col("sg").alias("to_sg")).distinct())
    there = Window.partitionBy("to_sg")
    picked = received.withColumn("received", F.count("*").over(there)).withColumn("centre_rank", (F.row_number().over(there.orderBy("key", "vid")) - 1).cast("int"))
    return picked.where(F.col("centre_rank") < k).select("to_sg", "received", "centre_rank", "vid")


def _arcs(g: PartitionedGraph) -> DataFrame:
    owners = g.vertices
    half = g.half_edges().select("u", "v", "weight")
    owned = half.join(owners.select(F.col("vid").alias("u"), F.col("sg").alias("su")), "u").join(owners.select(F.col("vid").alias("v"), F.col("sg").alias("sv")), "v")
    return owned.select("u", "v", "weight", "su", "sv")


def _assign_vertex(g: PartitionedGraph, centres: DataFrame, max_steps: int, log: MessageLog) -> tuple[DataFrame, int]:
    """A hop in each superstep: only vertices reached in the last one send, and a label once given is final."""
    arcs = spill(g.half_edges().select("u", "v"))
    front = spill(centres.select("vid", F.lit(0).alias("dist"), "centre_rank"))
    labels = front
    for step in range(1, max_steps + 1):
        sent = front.join(arcs, front["vid"] == arcs["u"]).groupBy(F.col("v").alias("vid")).agg(F.min("centre_rank").alias("centre_rank"), F.count("*").alias("asked"))
        fresh = sent.join(labels.select("vid"), "vid", "left_anti").select("vid", F.lit(step).alias("dist"), "centre_rank", "asked")
        fresh = spill(fresh)
        n, asked = fresh.agg(F.count("*"), F.coalesce(F.sum("asked"), F.lit(0))).first()
        log.add(Phase.ASSIGN, n, 0, asked)
        if not n:
            return labels, step
        front = fresh.select("vid", "dist", "centre_rank")
        labels = labels.unionByName(front)
    raise RuntimeError(f"labels did not settle in {max_steps} supersteps")


def _assign_subgraph(g: PartitionedGraph, centres: DataFrame, max_steps: int, log: MessageLog) -> tuple[DataFrame, int]:
    """A superstep is an exchange: messages over cut edges improve boundary labels, then each subgraph that was reached
    runs its inner hops to their fixpoint in memory; the vertices whose label changed send next."""
    import numpy as np
    import pyarrow as pa

    from .kernels import hops_within

    arcs = spill(_arcs(g))
    inner, cut = arcs.where("su = sv").select(F.col("su").alias("arc_sg"), "u", "v"), arcs.where("su <> sv").select("u", "v")
    seeded = g.vertices.select("vid", "sg").join(centres.select("vid", "centre_rank"), "vid", "left")
    none = F.lit(-1)
    state = spill(seeded.select("vid", "sg", F.when(F.col("centre_rank").isNull(), none).otherwise(0).cast("bigint").alias("dist"), F.coalesce("centre_rank", none).cast("bigint").alias("rank"), F.col("centre_rank").isNotNull().alias("hit")))

    def settle(key, rows: pa.Table, arcs_: pa.Table) -> pa.Table:
        vid, dist, rank, hit = (np.asarray(rows.column(c)) for c in ("vid", "dist", "rank", "hit"))
        d, r = hops_within(np.asarray(arcs_.column("u")), np.asarray(arcs_.column("v")), vid, dist, rank)
        return pa.table({"vid": vid, "sg": rows.column("sg"), "dist": d, "rank": r, "hit": hit | (d != dist) | (r != rank)})

    for step in range(1, max_steps + 1):
        active = state.where("hit").select("sg").distinct()
        busy = state.join(active, "sg", "left_semi")
        ran = busy.groupBy("sg").cogroup(inner.join(active.withColumnRenamed("sg", "arc_sg"), "arc_sg", "left_semi").groupBy("arc_sg")).applyInArrow(settle, "vid bigint, sg bigint, dist bigint, rank bigint, hit boolean")
        state = spill(ran.where("vid is not null").unionByName(state.join(active, "sg", "left_anti")), state)
        sent = state.where("hit").join(cut, F.col("vid") == F.col("u")).groupBy(F.col("v").alias("to")).agg(F.min(F.struct((F.col("dist") + 1).alias("dist"), "rank")).alias("m"), F.count("*").alias("asked"))
        old = F.struct(F.when(F.col("dist") < 0, F.lit(1 << 40)).otherwise(F.col("dist")).alias("dist"), "rank")
        better = F.coalesce(F.col("m") < old, F.lit(False))
        met = state.join(sent, F.col("vid") == F.col("to"), "left")
        merged = met.select("vid", "sg", F.when(better, F.col("m.dist")).otherwise(F.col("dist")).alias("dist"), F.when(better, F.col("m.rank")).otherwise(F.col("rank")).alias("rank"), better.alias("hit"), F.coalesce("asked", F.lit(0)).alias("asked"))
        merged = spill(merged, state)
        n, asked = merged.agg(F.count_if("hit"), F.coalesce(F.sum("asked"), F.lit(0))).first()
        log.add(Phase.ASSIGN, n, 0, asked)
        state = merged.drop("asked")
        if not n:
            forget(arcs)
            return merged.where("dist >= 0").select("vid", F.col("dist").cast("int").alias("dist"), F.col("rank").cast("int").alias("centre_rank")), step
        state._spilled = merged._spilled
    raise RuntimeError(f"labels did not settle in {max_steps} supersteps")


def assign(g: PartitionedGraph, centres: DataFrame, unit: str = "subgraph", max_steps: int = 1000, log: MessageLog | None = None) -> tuple[DataFrame, int]:
    """(vid, dist, centre_rank) of the reached vertices and the number of supersteps.

    ``vertex`` moves one hop in a superstep; in a ``subgraph`` superstep labels spread through whole subgraphs.
    """
    run = {"vertex": _assign_vertex, "subgraph": _assign_subgraph}[unit]
    return run(g, centres, max_steps, MessageLog() if log is None else log)


def assign_weighted(g: PartitionedGraph, centres: DataFrame, max_steps: int = 1000) -> DataFrame:
    """(vid, dist, centre_rank) by the least sum of edge weights: labels are corrected until none changes."""
    arcs = spill(g.half_edges())
    labels = spill(centres.select("vid", F.lit(0).cast("bigint").alias("dist"), "centre_rank", F.lit(True).alias("hit")))
    for _ in range(max_steps):
        moved = labels.where("hit").join(arcs, F.col("vid") == F.col("u")).select(F.col("v").alias("vid"), (F.col("dist") + F.col("weight")).alias("dist"), "centre_rank", F.lit(1).alias("new"))
        every = labels.select("vid", "dist", "centre_rank", F.lit(0).alias("new")).unionByName(moved)
        best = every.groupBy("vid").agg(F.min(F.struct("dist", "centre_rank", "new")).alias("x"))
        labels = spill(best.select("vid", "x.dist", "x.centre_rank", (F.col("x.new") == 1).alias("hit")), labels)
        if labels.where("hit").isEmpty():
            return labels.drop("hit")
    raise RuntimeError(f"labels did not settle in {max_steps} steps")


def edge_cut(g: PartitionedGraph, labels: DataFrame) -> DataFrame:
    """(local_cut, remote_cut): edges between clusters inside a subgraph and across; unreached vertices are one cluster."""
    lab = lambda end: labels.select(F.col("vid").alias(end), F.col("centre_rank").alias(f"{end}_rank"))
    e = g.owned_edges().join(lab("src"), "src", "left").join(lab("dst"), "dst", "left").where(~F.col("src_rank").eqNullSafe(F.col("dst_rank")))
    return e.agg(F.count_if(F.col("src_sg") == F.col("dst_sg")).alias("local_cut"), F.count_if(F.col("src_sg") != F.col("dst_sg")).alias("remote_cut"))


def kway_cluster(g: PartitionedGraph, k: int, tau: int, seed: int = 7, max_rounds: int = 10, unit: str = "subgraph", strict: bool = False, sampling: str = "reservoir") -> tuple[DataFrame, dict]:
    """Labels of the first round whose cut is at most ``tau`` (below it, if ``strict``), else of the best round."""
    best = None
    for r in range(max_rounds):
        labels, steps = assign(g, draw_centres(g, k, seed, r, sampling), unit)
        row = edge_cut(g, labels).first()
        cut = row["local_cut"] + row["remote_cut"]
        if best is None or cut < best[1]["cut"]:
            best = labels, {"round": r, "cut": cut, "supersteps": steps, "accepted": False}
        if cut < tau or (cut == tau and not strict):
            best = labels, {"round": r, "cut": cut, "supersteps": steps, "accepted": True}
            break
    return best[0], best[1] | {"rounds": r + 1}


def cluster_summary(g: PartitionedGraph, labels: DataFrame) -> DataFrame:
    """(centre_rank, vertices, radius, inner_edges, cut_edges): shape of each cluster."""
    lab = lambda end: labels.select(F.col("vid").alias(end), F.col("centre_rank").alias(f"{end}_rank"))
    e = g.edges.join(lab("src"), "src", "left").join(lab("dst"), "dst", "left")
    same = F.col("src_rank").eqNullSafe(F.col("dst_rank"))
    ends = e.select(F.explode(F.when(same, F.array("src_rank")).otherwise(F.array("src_rank", "dst_rank"))).alias("centre_rank"), same.alias("inner")).where("centre_rank is not null")
    edges = ends.groupBy("centre_rank").agg(F.count_if("inner").alias("inner_edges"), F.count_if(~F.col("inner")).alias("cut_edges"))
    sizes = labels.groupBy("centre_rank").agg(F.count("*").alias("vertices"), F.max("dist").cast("bigint").alias("radius"))
    zero = F.lit(0).cast("bigint")
    return sizes.join(edges, "centre_rank", "left").select("centre_rank", "vertices", "radius", F.coalesce("inner_edges", zero).alias("inner_edges"), F.coalesce("cut_edges", zero).alias("cut_edges"))


def check_clusters(g: PartitionedGraph, labels: DataFrame) -> DataFrame:
    """(centre_rank, vertices, pieces): a valid cluster is one connected piece; no vertex is in two."""
    lab = lambda end: labels.select(F.col("vid").alias(end), F.col("centre_rank").alias(f"{end}_rank"))
    inner = g.edges.join(lab("src"), "src").join(lab("dst"), "dst").where("src_rank = dst_rank").select("src", "dst")
    piece = labels.join(connected_components(inner), "vid", "left")
    return piece.groupBy("centre_rank").agg(F.count("*").alias("vertices"), F.countDistinct(F.coalesce("comp", "vid")).alias("pieces"))
