"""Minimum spanning forest by hooking along least edges: inside subgraphs first, then in rounds between roots."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.graphs import PartitionedGraph
from ..storage import spill

EDGE = "src bigint, dst bigint, weight bigint"
#: Contracted edges that one task finishes at once, where the caller allows it.
FINISH_EDGES = 200_000


def _roots(asks: DataFrame) -> tuple[DataFrame, int]:
    """(r, root) of asking roots, and pointer-jump steps; of a mutual pair the smaller id becomes the root."""
    back = asks.select(F.col("to").alias("r"), F.col("r").alias("to"), F.lit(True).alias("mutual"))
    top = F.coalesce(F.col("mutual"), F.lit(False)) & (F.col("r") < F.col("to"))
    parent = spill(asks.join(back, ["r", "to"], "left").select("r", F.when(top, F.col("r")).otherwise(F.col("to")).alias("root")))
    steps = 0
    while True:
        up = parent.select(F.col("r").alias("root"), F.col("root").alias("above"))
        jumped = spill(parent.join(up, "root", "left").select("r", F.col("root").alias("was"), F.coalesce("above", "root").alias("root")), parent)
        steps += 1
        parent = jumped.select("r", "root")
        parent._spilled = jumped._spilled
        if jumped.where("was <> root").isEmpty():
            return parent, steps


def contract(edges: DataFrame, parent: DataFrame) -> DataFrame:
    """Edges between the new roots, the least of each pair; the original ends travel along."""
    for side in ("ra", "rb"):
        edges = edges.join(parent.select(F.col("r").alias(side), F.col("root").alias("new")), side, "left").withColumn(side, F.coalesce("new", side)).drop("new")
    apart = edges.where("ra <> rb").withColumns({"x": F.least("ra", "rb"), "y": F.greatest("ra", "rb")})
    least = apart.groupBy("x", "y").agg(F.min(F.struct("weight", "src", "dst", "inner")).alias("k"))
    return least.select(F.col("x").alias("ra"), F.col("y").alias("rb"), "k.weight", "k.src", "k.dst", "k.inner")


def _questions(edges: DataFrame) -> DataFrame:
    """(r, to, weight, src, dst, inner): each root asks along its least edge."""
    key = F.struct("weight", "src", "dst")
    ends = edges.select(F.col("ra").alias("r"), F.col("rb").alias("to"), key.alias("k"), "inner").union(edges.select("rb", "ra", key, "inner"))
    return ends.groupBy("r").agg(F.min(F.struct("k", "to", "inner")).alias("x")).select("r", "x.to", "x.k.weight", "x.k.src", "x.k.dst", "x.inner")


def local_forest(g: PartitionedGraph) -> DataFrame:
    """(is_edge, src, dst, weight): chosen inner edges, and rows (vertex, root) where ``is_edge`` is false.

    Each subgraph merges its trees in memory along least edges while these are inner; trees whose least edge is remote wait.
    """
    import numpy as np
    import pyarrow as pa

    from .kernels import forest_within

    inner = F.col("src_sg") == F.col("dst_sg")
    sides = F.when(inner, F.array("src_sg")).otherwise(F.array("src_sg", "dst_sg"))
    rows = g.owned_edges().select("src", "dst", "weight", inner.alias("inner"), F.explode(sides).alias("sg"))

    def run(table: pa.Table) -> pa.Table:
        src, dst, weight, flag = (np.asarray(table.column(c)) for c in ("src", "dst", "weight", "inner"))
        chosen, vid, root = forest_within(src, dst, weight, flag)
        moved = vid != root
        return pa.table({
            "is_edge": np.concatenate([np.ones(int(chosen.sum()), bool), np.zeros(int(moved.sum()), bool)]),
            "src": np.concatenate([src[chosen], vid[moved]]),
            "dst": np.concatenate([dst[chosen], root[moved]]),
            "weight": np.concatenate([weight[chosen], np.zeros(int(moved.sum()), np.int64)]),
        })

    return rows.groupBy("sg").applyInArrow(run, f"is_edge boolean, {EDGE}")


def _finished(edges: DataFrame) -> DataFrame:
    """The rest of the forest in one task: (is_edge, src, dst, weight) as of ``local_forest``, between roots."""
    import numpy as np
    import pyarrow as pa

    from .kernels import forest_within

    def run(table: pa.Table) -> pa.Table:
        ra, rb, weight, src, dst = (np.asarray(table.column(c)) for c in ("ra", "rb", "weight", "src", "dst"))
        order = np.empty(len(ra), np.int64)
        order[np.lexsort((dst, src, weight))] = np.arange(len(ra))
        chosen, vid, root = forest_within(ra, rb, order, np.ones(len(ra), bool))
        moved = vid != root
        return pa.table({
            "is_edge": np.concatenate([np.ones(int(chosen.sum()), bool), np.zeros(int(moved.sum()), bool)]),
            "src": np.concatenate([src[chosen], vid[moved]]),
            "dst": np.concatenate([dst[chosen], root[moved]]),
            "weight": np.concatenate([weight[chosen], np.zeros(int(moved.sum()), np.int64)]),
        })

    return edges.withColumn("one", F.lit(1)).groupBy("one").applyInArrow(run, f"is_edge boolean, {EDGE}")


def spanning_forest(g: PartitionedGraph, unit: str = "subgraph", max_rounds: int = 200, finish: int = 0, literal_halt: bool = False) -> tuple[DataFrame, DataFrame, list[dict]]:
    """(forest edges src, dst, weight, phase, round; tree of each vertex vid, root; log of rounds).

    ``subgraph``: every subgraph first merges its own trees in memory; then roots ask along their least edges, round by
    round. ``vertex``: rounds alone. ``single``: the whole graph as one subgraph in one task (shared memory). ``filter``:
    each subgraph drops the inner edges that are not in its own forest, then rounds. Ties are broken by (weight, src, dst).
    At most ``finish`` contracted edges are finished by one task. ``literal_halt`` stops, as printed, when no root's least
    edge joins two subgraphs, which may be too early.
    """
    if unit not in ("subgraph", "vertex", "single", "filter"):
        raise ValueError(unit)
    base = PartitionedGraph(g.vertices, spill(own_forests(g))) if unit == "filter" else g
    own = base.owned_edges()
    edges = own.select(F.col("src").alias("ra"), F.col("dst").alias("rb"), "weight", "src", "dst", (F.col("src_sg") == F.col("dst_sg")).alias("inner"))
    tree = g.vertices.select("vid", F.col("vid").alias("root"))
    chosen, log = [], []

    def follow(parent: DataFrame) -> DataFrame:
        return tree.join(parent.select(F.col("r").alias("root"), F.col("root").alias("new")), "root", "left").select("vid", F.coalesce("new", "root").alias("root"))

    def take(rows: DataFrame, phase: str, round_: int) -> DataFrame:
        chosen.append(rows.where("is_edge").select("src", "dst", "weight").withColumns({"phase": F.lit(phase), "round": F.lit(round_)}))
        return rows.where("not is_edge").select(F.col("src").alias("r"), F.col("dst").alias("root"))

    edges, tree = spill(edges), spill(tree)
    if unit == "subgraph":
        local = spill(local_forest(g))
        parent = take(local, "local", 0)
        n = chosen[0].count()
        log.append({"round": 0, "phase": "local", "asks": n, "jumps": 0})
        if n:
            tree, edges = spill(follow(parent), tree), spill(contract(edges, parent), edges)
    for round_ in range(len(log), max_rounds):
        left = edges.count()
        if left and (unit == "single" or left <= finish):
            rest = spill(_finished(edges))
            parent = take(rest, "finish", round_)
            tree = spill(follow(parent), tree)
            log.append({"round": round_, "phase": "finish", "asks": left, "jumps": 0})
            break
        asks = _questions(edges)
        asks = spill(asks.where("not inner") if literal_halt else asks)
        n = asks.count()
        if not n:
            break
        chosen.append(asks.select("src", "dst", "weight").distinct().withColumns({"phase": F.lit("remote"), "round": F.lit(round_)}))
        parent, jumps = _roots(asks.select("r", "to"))
        tree, edges = spill(follow(parent), tree), spill(contract(edges, parent), edges)
        log.append({"round": round_, "phase": "remote", "asks": n, "jumps": jumps})
    else:
        raise RuntimeError(f"forest not done in {max_rounds} rounds")
    out = g.edges.where("false").select("src", "dst", "weight", F.lit("local").alias("phase"), F.lit(0).alias("round"))
    for c in chosen:
        out = out.unionByName(c)
    low = tree.groupBy("root").agg(F.min("vid").alias("least"))
    return out, tree.join(low, "root").select("vid", F.col("least").alias("root")), log


def own_forests(g: PartitionedGraph) -> DataFrame:
    """(src, dst, weight): all cut edges, and of the inner edges those in their subgraph's own forest."""
    import numpy as np
    import pyarrow as pa

    from .kernels import forest_within

    own = g.owned_edges()
    same = F.col("src_sg") == F.col("dst_sg")

    def run(table: pa.Table) -> pa.Table:
        cols = [np.asarray(table.column(c)) for c in ("src", "dst", "weight")]
        chosen = forest_within(*cols, np.ones(len(table), bool))[0]
        return table.select(["src", "dst", "weight"]).filter(pa.array(chosen))

    kept = own.where(same).select("src", "dst", "weight", F.col("src_sg").alias("sg")).groupBy("sg").applyInArrow(run, EDGE)
    return kept.unionByName(own.where(~same).select("src", "dst", "weight"))


def forest_summary(g: PartitionedGraph, forest: DataFrame) -> DataFrame:
    """(edges, weight, trees): each edge joins two trees of what were single vertices."""
    f = forest.agg(F.count("*").alias("edges"), F.coalesce(F.sum("weight"), F.lit(0)).alias("weight"))
    return f.crossJoin(g.vertices.agg(F.count("*").alias("n"))).select("edges", "weight", (F.col("n") - F.col("edges")).alias("trees"))


def single_linkage(g: PartitionedGraph, forest: DataFrame, drop: int) -> DataFrame:
    """(vid, cluster): components of the forest without its ``drop`` heaviest edges; a cluster is named by its least vertex."""
    from .components import connected_components

    edges = spill(forest.select("src", "dst", "weight"))
    gone = edges.orderBy(F.desc("weight"), F.desc("src"), F.desc("dst")).limit(drop)
    comp = connected_components(edges.join(gone.select("src", "dst"), ["src", "dst"], "left_anti"))
    return g.vertices.select("vid").join(comp, "vid", "left").select("vid", F.coalesce("comp", "vid").alias("cluster"))
