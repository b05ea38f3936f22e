"""Triangles (a < b < c, once each): one-plan and superstep subgraph forms, vertex-centric and shared-memory baselines."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.graphs import PartitionedGraph, met_pairs
from ..storage import spill

NAMES = ["a", "b", "c"]


def _sorted(x, y, z):
    ids = F.array_sort(F.array(x, y, z))
    return [ids[i].alias(n) for i, n in enumerate(NAMES)]


def _owned(g: PartitionedGraph) -> tuple[DataFrame, DataFrame]:
    e = g.owned_edges().select("src", "dst", "src_sg", "dst_sg")
    return e.where("src_sg = dst_sg"), e.where("src_sg <> dst_sg")


def _wedges(first: DataFrame, second: DataFrame) -> DataFrame:
    """(v, w, u) with owners, v < w < u, over an edge of each table that meet at w."""
    x = first.select(F.col("src").alias("v"), F.col("dst").alias("w"), F.col("src_sg").alias("v_sg"), F.col("dst_sg").alias("w_sg"))
    y = second.select(F.col("src").alias("w"), F.col("dst").alias("u"), F.col("dst_sg").alias("u_sg"))
    return x.join(y, "w")


def _closed(wedges: DataFrame, edges: DataFrame) -> DataFrame:
    close = edges.select(F.col("src").alias("v"), F.col("dst").alias("u"))
    return wedges.join(close, ["v", "u"], "left_semi")


def _local_types(inner: DataFrame, cut: DataFrame) -> DataFrame:
    """Types i and ii: three inner edges, or an inner edge with two cut edges to one vertex."""
    one = _closed(_wedges(inner, inner), inner).select(F.col("v").alias("a"), F.col("w").alias("b"), F.col("u").alias("c"), F.lit("i").alias("tri_type"))
    half = cut.select(F.col("src").alias("own"), F.col("dst").alias("far")).union(cut.select("dst", "src"))
    left = inner.select("src", "dst").join(half.select(F.col("own").alias("src"), "far"), "src")
    two = left.join(half.select(F.col("own").alias("dst"), "far"), ["dst", "far"], "left_semi").select(*_sorted("src", "dst", "far"), F.lit("ii").alias("tri_type"))
    return one.unionByName(two)


#: Edges that a cell of the closing test holds, about (its arrays need some 25 bytes an edge).
CELL_EDGES = 12_000_000
#: Least number of colours: with 3 there are 10 cells.
COLOURS = 3
#: Listed triangles that are handed to Spark at once.
LISTED_ROWS = 1 << 17
#: Edges that a task packs at once.
PACKED_EDGES = 4_000_000
#: Triangle kinds: one owner, the alone vertex of a type ii (first, middle or last of a < b < c), three owners.
KINDS = ("i", "first", "middle", "last", "iii")
#: Stands for the owner null, which equals no other.
NO_OWNER = -(1 << 63)


def _packed(edges: DataFrame, colours: int) -> DataFrame:
    """(p, q, blob): edges packed by the colours p <= q of their ends, some millions at a time."""
    import numpy as np
    import pyarrow as pa

    from .kernels import colour_of, packed_edges

    def flush(held: list[pa.RecordBatch]) -> pa.RecordBatch:
        src, dst = (np.concatenate([np.asarray(b.column(c)) for b in held]) for c in (0, 1))
        i, j = colour_of(src, colours), colour_of(dst, colours)
        pair = np.minimum(i, j) * colours + np.maximum(i, j)
        found = np.unique(pair)
        blobs = [packed_edges(src[pair == x], dst[pair == x]) for x in found]
        return pa.RecordBatch.from_arrays([pa.array((found // colours).astype(np.int32)), pa.array((found % colours).astype(np.int32)), pa.array(blobs, pa.binary())], ["p", "q", "blob"])

    def run(batches):
        held, n = [], 0
        for batch in batches:
            held.append(batch)
            n += len(batch)
            if n >= PACKED_EDGES:
                yield flush(held)
                held, n = [], 0
        if n:
            yield flush(held)

    return edges.select(F.col("src").cast("bigint"), F.col("dst").cast("bigint")).mapInArrow(run, "p int, q int, blob binary")


def _packed_vertices(vertices: DataFrame, colours: int) -> DataFrame:
    """(p, blob): vid, owner and weight of the vertices of each colour."""
    import numpy as np
    import pyarrow as pa

    from .kernels import colour_of, packed_longs

    def run(batches):
        for batch in batches:
            cols = [np.asarray(c) for c in batch.columns]
            colour = colour_of(cols[0], colours)
            found = np.unique(colour)
            blobs = [packed_longs(*(c[colour == x] for c in cols)) for x in found]
            yield pa.RecordBatch.from_arrays([pa.array(found.astype(np.int32)), pa.array(blobs, pa.binary())], ["p", "blob"])

    weight = F.col("weight").cast("bigint") if "weight" in vertices.columns else F.lit(1).cast("bigint").alias("weight")
    sg = F.coalesce(F.col("sg").cast("bigint"), F.lit(NO_OWNER))
    return vertices.where("vid is not null").select(F.col("vid").cast("bigint"), sg, weight).mapInArrow(run, "p int, blob binary")


def _colours(edges: int) -> int:
    return max(COLOURS, math.ceil(math.sqrt(6 * edges / CELL_EDGES)))


def in_cells(edges: DataFrame, count: bool, by: str = "degree", colours: int | None = None, vertices: DataFrame | None = None) -> DataFrame:
    """All triangles of ``edges`` (src, dst): (a, b, c, kind, own), or (kind, own, triangles) if counted.

    Owners come from ``vertices`` (vid, sg; edges with an end beyond these play no part) or from columns src_sg and dst_sg
    of the edges; with neither, all vertices have one owner. ``own`` is the owner that two or three vertices share (-1 for
    kind iii: none). With a column ``weight`` in ``vertices``, a triangle counts as the product of its vertices' weights.

    Vertices are hashed to colours, an edge goes to each cell (three colours, repeats allowed) that holds both of its
    colours, and a triangle belongs to the cell of exactly its colours. Edges travel packed, a few bytes each, as often as
    there are colours, and no two-step path is shuffled. Dense cells are counted by rows of bits.
    """
    import numpy as np
    import pyarrow as pa

    from .kernels import bits_are_cheaper, closing_counts, closing_paths, colour_of, unpacked_edges, unpacked_longs

    owned = vertices is not None or "src_sg" in edges.columns
    weighted = vertices is not None and "weight" in vertices.columns
    if colours is None:
        edges = spill(edges.select("src", "dst", *(["src_sg", "dst_sg"] if owned and vertices is None else [])))
        colours = _colours(edges.count())
    if owned and vertices is None:
        vertices = edges.select(F.col("src").alias("vid"), F.col("src_sg").alias("sg")).union(edges.select("dst", "dst_sg")).distinct()
    other = F.explode(F.sequence(F.lit(0), F.lit(colours - 1)))
    met = F.array_sort(F.array("p", "q", "k"))
    cell = ((met[0] * colours + met[1]) * colours + met[2]).alias("cell")
    rows = _packed(edges, colours).withColumn("k", other).select(cell, F.lit(True).alias("edges"), "blob")
    if owned:
        seen = _packed_vertices(vertices, colours).withColumn("q", other).withColumn("k", other).where("q <= k")
        rows = rows.unionByName(seen.select(cell, F.lit(False).alias("edges"), "blob"))

    def run(batches):
        table = pa.Table.from_batches(batches)
        code = int(table.column("cell")[0].as_py())
        paint = [code // colours // colours, code // colours % colours, code % colours]
        kept = np.asarray(table.column("edges").combine_chunks().to_numpy(zero_copy_only=False), bool)
        blobs = table.column("blob")
        mine = [int(x) for x in np.flatnonzero(kept)]
        if owned:
            vid, sg, weight = (np.concatenate(x) for x in zip(*([unpacked_longs(blobs[int(x)].as_py(), 3) for x in np.flatnonzero(~kept)] or [[np.zeros(0, np.int64)] * 3]), strict=True))
            ids, at = np.unique(vid, return_index=True)
            sg, weight = sg[at], weight[at]
        else:
            ids = np.zeros(0, np.int64)
            for x in mine:
                ids = np.union1d(ids, unpacked_edges(blobs[x].as_py())[0])
            sg, weight = np.zeros(len(ids), np.int64), np.ones(len(ids), np.int64)
        ends: list[list] = [[], []]
        for x in mine:
            own, s, d = unpacked_edges(blobs[x].as_py())
            at = np.minimum(np.searchsorted(ids, own), max(0, len(ids) - 1))
            there = ids[at] == own if len(ids) else np.zeros(len(own), bool)
            at = at.astype(np.int32)
            if not there.all():
                both = there[s] & there[d]
                s, d = s[both], d[both]
            ends[0].append(at[s])
            ends[1].append(at[d])
        del blobs, table
        s, d = (np.concatenate(x) if x else np.zeros(0, np.int32) for x in ends)
        del ends
        # owners as small numbers, a null one unlike all others
        owners, own = np.unique(sg, return_inverse=True)
        null = np.flatnonzero(sg == NO_OWNER)
        own[null] = len(owners) + np.arange(len(null))
        if count and not weighted and bits_are_cheaper(s, d, len(ids), len(owners) + len(null)):
            total = closing_counts(s, d, len(ids), own, len(owners) + len(null), colour_of(ids, colours), paint)
            many: dict = {}
            for p, q, r in np.argwhere(total).tolist():
                if not owned or p == q == r:
                    kind, mate = "i", p
                else:
                    kind, mate = ("first", q) if q == r else ("middle", p) if p == r else ("last", p) if p == q else ("iii", None)
                line = kind, -1 if mate is None else int(owners[mate]) if owned else 0
                many[line] = many.get(line, 0) + int(total[p, q, r])
            cols = [[k for k, _ in many], [o for _, o in many], list(many.values())]
            yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.string()), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.int64())], ["kind", "own", "triangles"])
            return
        back, found = closing_paths(s, d, len(ids), by)
        del s, d
        # by rank
        group, load = own[back].astype(np.int32), weight[back]
        # a cell of two colours sees triangles of the repeated one too, which belong to another cell
        twice = paint[1] if len(set(paint)) == 2 else None
        alike = None if twice is None else colour_of(ids[back], colours) == twice
        three, many = 0, {}
        held: list[tuple] = []

        def settle() -> None:
            if held:
                keys, n = (np.concatenate(x) for x in zip(*held, strict=True))
                distinct, at = np.unique(keys, return_inverse=True)
                total = np.zeros(len(distinct), np.int64)
                np.add.at(total, at, n) if weighted else np.copyto(total, np.bincount(at, minlength=len(distinct)))
                for x, c in zip(distinct.tolist(), total.tolist(), strict=True):
                    many[x] = many.get(x, 0) + c
                held.clear()

        size = 0
        for x, y, z in found:
            if alike is not None:
                right = ~(alike[x] & alike[y] & alike[z])
                x, y, z = x[right], y[right], z[right]
            if count and not owned:
                three += len(x)
                continue
            p, q, r = group[x], group[y], group[z]
            xy, xz, yz = p == q, p == r, q == r
            some = xy | xz | yz
            if count:
                n = load[x] * load[y] * load[z] if weighted else None
                if weighted and float((load[x].astype(float) * load[y] * load[z]).sum()) > 9e18:
                    raise OverflowError("more triangles than a bigint holds")
                three += int(n[~some].sum()) if weighted else len(x) - int(np.count_nonzero(some))
                some = np.flatnonzero(some)
                x, y, z, p, q, xy, xz, yz = (v[some] for v in (x, y, z, p, q, xy, xz, yz))
            a, b, c = back[x], back[y], back[z]
            alone = np.where(xy & xz, -1, np.where(yz, a, np.where(xz, b, c)))
            kind = np.where(alone < 0, 0, 1 + (alone > np.minimum(np.minimum(a, b), c)) + (alone == np.maximum(np.maximum(a, b), c)))
            mate = np.where(yz, q, p)
            if count:
                held.append((mate.astype(np.int64) * 4 + kind, n[some] if weighted else kind))
                size += len(kind)
                if size > 1 << 22:
                    settle()
                    size = 0
            else:
                kind = np.where(some, kind, 4)
                shared = owners[np.where(some, mate, 0)]
                cols = [*ids[np.sort(np.stack([a, b, c]), axis=0)], pa.DictionaryArray.from_arrays(kind.astype(np.int8), KINDS).cast(pa.string()), np.where(some, shared, -1)]
                yield from pa.table(dict(zip(("a", "b", "c", "kind", "own"), cols, strict=True))).to_batches(max_chunksize=LISTED_ROWS)
        if count:
            settle()
            lines = [(KINDS[x % 4], int(owners[x // 4]), c) for x, c in many.items()]
            if three:
                lines.append(("iii", -1, three) if owned else ("i", 0, three))
            cols = list(zip(*lines, strict=True)) or [[]] * 3
            yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.string()), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.int64())], ["kind", "own", "triangles"])

    # Spark streams the batches of a group to functions so marked: listed triangles are never held together
    run.__annotations__ = {"batches": Iterator[pa.RecordBatch], "return": Iterator[pa.RecordBatch]}
    if count:
        found = rows.groupBy("cell").applyInArrow(run, "kind string, own bigint, triangles bigint")
        return found.groupBy("kind", "own").agg(F.sum("triangles").alias("triangles"))
    return rows.groupBy("cell").applyInArrow(run, "a bigint, b bigint, c bigint, kind string, own bigint")


def _owned_cells(g: PartitionedGraph, count: bool) -> DataFrame:
    return in_cells(g.edges.select("src", "dst"), count, vertices=g.vertices)


def _type():
    return F.when(F.col("kind").isin("i", "iii"), F.col("kind")).otherwise("ii").alias("tri_type")


def triangles(g: PartitionedGraph) -> DataFrame:
    """(a, b, c, tri_type): 3 inner edges, an inner edge with two cut edges to one vertex, 3 cut edges."""
    return _owned_cells(g, False).select(*NAMES, _type())


def count_types(g: PartitionedGraph) -> DataFrame:
    """(tri_type, triangles): the same without a row for each triangle."""
    return _owned_cells(g, True).groupBy(_type()).agg(F.sum("triangles").alias("triangles"))


def _total(edges: DataFrame, by: str) -> DataFrame:
    """(triangles), one row, with edges taken by id or by degree; owners play no part."""
    return in_cells(edges.select("src", "dst"), True, by).agg(F.coalesce(F.sum("triangles"), F.lit(0)).alias("triangles"))


def triangles_bsp(g: PartitionedGraph, mode: str = "complete", prune: bool = False) -> tuple[DataFrame, list[dict]]:
    """Triangles and the log of supersteps (superstep, found, messages); stops as soon as a round sends nothing.

    ``as_printed`` finds locally only those whose two smaller vertices share a subgraph, and never those whose smallest
    vertex is alone; ``receive_check`` adds them where the first message arrives; ``complete`` finds all of types i and
    ii in the first step and sends only what may span three subgraphs. ``prune`` (complete only): a cut edge (v, w) is
    sent only if v has another larger neighbour, outside both subgraphs, that may close the triangle.
    """
    if mode not in ("complete", "as_printed", "receive_check"):
        raise ValueError(mode)
    owned = spill(g.owned_edges().select("src", "dst", "src_sg", "dst_sg"))
    inner, cut = owned.where("src_sg = dst_sg"), owned.where("src_sg <> dst_sg")
    plain = lambda d: d.select(F.col("v").alias("a"), F.col("w").alias("b"), F.col("u").alias("c"))
    if mode == "complete":
        local = _local_types(inner, cut).select(*NAMES)
    else:
        local = plain(_closed(_wedges(inner, owned), owned))
    found, log = [spill(local)], []
    asked = sent_pairs(cut) if prune and mode == "complete" else cut
    sent = asked.count()
    log.append({"superstep": 0, "found": found[0].count(), "messages": sent})
    if not sent:
        return found[0], log
    second = _wedges(asked, cut)
    forwarded = spill(second.where("v_sg <> u_sg") if mode == "complete" else second)
    n = 0
    if mode == "receive_check":
        found.append(spill(plain(_closed(_wedges(cut, inner), cut))))
        n = found[-1].count()
    sent = forwarded.count()
    log.append({"superstep": 1, "found": n, "messages": sent})
    if sent:
        found.append(spill(plain(_closed(forwarded, owned)), forwarded))
        log.append({"superstep": 2, "found": found[-1].count(), "messages": 0})
    return reduce(DataFrame.unionByName, found), log


def sent_pairs(cut: DataFrame) -> DataFrame:
    """The cut edges (v, w) worth sending: v has a larger neighbour beyond w, in neither's subgraph."""
    other = cut.select(F.col("src").alias("o_src"), F.col("dst").alias("o_dst"), F.col("dst_sg").alias("o_sg"))
    return cut.join(other, (cut["src"] == F.col("o_src")) & (F.col("o_dst") > cut["dst"]) & (F.col("o_sg") != cut["dst_sg"]), "left_semi")


#: Edges of one subgraph (cut edges included) that its kernel takes into memory at once; larger subgraphs go relational.
KERNEL_EDGES = 4_000_000
TYPED = "a bigint, b bigint, c bigint, tri_type string"


def _with_kernel(g: PartitionedGraph, count: bool, cap: int | None) -> DataFrame:
    """All triangles, listed or counted by type: types i and ii by a shared-memory routine in each subgraph, type iii in
    cells of the cut edges.

    Where a subgraph has more than ``cap`` edges, one pass over cells of all edges gives the types of these subgraphs and
    type iii; the smaller ones keep their routine. ``cap`` None: all subgraphs are known to fit into memory.
    """
    import numpy as np
    import pyarrow as pa

    from .kernels import triangles_with_inner_edge

    owned = g.owned_edges().select("src", "dst", "src_sg", "dst_sg")
    if cap is not None:
        owned = spill(owned)  # read for the sizes and for each part
    inner = F.col("src_sg") == F.col("dst_sg")
    sides = F.when(inner, F.array("src_sg")).otherwise(F.array("src_sg", "dst_sg"))
    rows = owned.select("src", "dst", inner.alias("inner"), F.explode(sides).alias("sg"))

    def run(batches):
        table = pa.Table.from_batches(batches)
        src, dst, flag = (np.asarray(table.column(c)) for c in ("src", "dst", "inner"))
        del table
        ones = twos = 0
        for a, b, c, whole in triangles_with_inner_edge(src, dst, flag):
            if count:
                ones, twos = ones + int(whole.sum()), twos + int((~whole).sum())
            else:
                yield from pa.table({"a": a, "b": b, "c": c, "tri_type": pa.array(np.where(whole, "i", "ii"), pa.string())}).to_batches(max_chunksize=LISTED_ROWS)
        if count:
            yield pa.RecordBatch.from_arrays([pa.array(["i", "ii"]), pa.array([ones, twos], pa.int64())], ["tri_type", "triangles"])

    run.__annotations__ = {"batches": Iterator[pa.RecordBatch], "return": Iterator[pa.RecordBatch]}
    schema = "tri_type string, triangles bigint" if count else TYPED
    big = None
    if cap is not None:
        # map-side sums: one row for each subgraph is shuffled
        big = spill(rows.groupBy("sg").agg(F.count("*").alias("n")).where(F.col("n") > cap).select("sg"))
        if big.isEmpty():
            big = None
    if big is None:
        local = rows.groupBy("sg").applyInArrow(run, schema)
        cells = in_cells(owned.where("src_sg <> dst_sg").select("src", "dst"), count, vertices=g.vertices).where("kind = 'iii'")
    else:
        local = rows.join(big, "sg", "left_anti").groupBy("sg").applyInArrow(run, schema)
        held = big.select(F.col("sg").alias("own"), F.lit(True).alias("big"))
        cells = in_cells(owned.select("src", "dst"), count, colours=_colours(owned.count()), vertices=g.vertices).join(held, "own", "left").where("kind = 'iii' or big")
    if count:
        return local.unionByName(cells.select(_type(), "triangles")).groupBy("tri_type").agg(F.sum("triangles").alias("triangles")).where("triangles > 0")
    return local.unionByName(cells.select(*NAMES, _type()))


def triangles_kernel(g: PartitionedGraph, cap: int | None = KERNEL_EDGES) -> DataFrame:
    """(a, b, c, tri_type): each subgraph finds types i and ii in memory; only cut edges are met in cells for type iii."""
    return _with_kernel(g, False, cap)


def count_kernel(g: PartitionedGraph, cap: int | None = KERNEL_EDGES) -> DataFrame:
    """(tri_type, triangles): the same without listing types i and ii."""
    return _with_kernel(g, True, cap)


def triangles_vertex_centric(g: PartitionedGraph) -> DataFrame:
    """Baseline in three supersteps: ids to larger neighbours, forwarded to larger ones, closing test."""
    e = g.edges.select("src", "dst")
    asked = e.select(F.col("src").alias("v"), F.col("dst").alias("w"))
    forwarded = asked.join(e.select(F.col("src").alias("w"), F.col("dst").alias("u")), "w")
    return _closed(forwarded, e).select(F.col("v").alias("a"), F.col("w").alias("b"), F.col("u").alias("c"))


def count_vertex_centric(g: PartitionedGraph) -> DataFrame:
    """(triangles): the same paths over growing ids and the same closing test, which meet in cells; nothing is listed."""
    return _total(g.edges, "id")


def triangles_node_iterator(g: PartitionedGraph) -> DataFrame:
    """Baseline: every pair of larger neighbours of a node is tested."""
    e = g.edges.select("src", "dst")
    pairs = e.alias("x").join(e.alias("y"), F.expr("x.src = y.src and x.dst < y.dst")).select(F.col("x.src").alias("a"), F.col("x.dst").alias("v"), F.col("y.dst").alias("u"))
    return _closed(pairs, e).select("a", F.col("v").alias("b"), F.col("u").alias("c"))


def degrees(g: PartitionedGraph) -> DataFrame:
    """(vid, degree) of vertices with an edge."""
    return g.edges.select(F.explode(F.array("src", "dst")).alias("vid")).groupBy("vid").agg(F.count("*").alias("degree"))


def triangles_forward(g: PartitionedGraph) -> DataFrame:
    """Baseline: edges point to the larger (degree, id), which bounds out-degrees by sqrt(2m); out-lists intersect."""
    arcs = orient(g, "degree")
    outs = arcs.groupBy("lo").agg(F.collect_list("hi").alias("out"))
    met = arcs.join(outs, "lo").join(outs.select(F.col("lo").alias("hi"), F.col("out").alias("far")), "hi")
    return met.select("lo", "hi", F.explode(F.array_intersect("out", "far")).alias("u")).select(*_sorted("lo", "hi", "u"))


def message_counts(g: PartitionedGraph) -> DataFrame:
    """(form, round, messages): what each form sends, without running it."""
    e = g.owned_edges()
    cut = e.where("src_sg <> dst_sg")
    row = lambda df, form, k: df.agg(F.count("*").alias("messages")).select(F.lit(form).alias("form"), F.lit(k).alias("round"), "messages")
    outs = e.groupBy(F.col("src").alias("w")).agg(F.count("*").alias("o"))
    ins = e.groupBy(F.col("dst").alias("w")).agg(F.count("*").alias("i"))
    through = ins.join(outs, "w").agg(F.coalesce(F.sum(F.col("i") * F.col("o")), F.lit(0)).alias("messages")).select(F.lit("vertex").alias("form"), F.lit(2).alias("round"), "messages")
    parts = [row(e, "vertex", 1), through, row(cut, "subgraph", 1), row(_wedges(cut, cut).where("v_sg <> u_sg"), "subgraph", 2)]
    return reduce(DataFrame.unionByName, parts)


def open_wedges(g: PartitionedGraph) -> DataFrame:
    """(v, w, u), v < w < u, over three subgraphs and not closed."""
    _, cut = _owned(g)
    ends = cut.select(F.col("src").alias("v"), F.col("dst").alias("u"))
    return _wedges(cut, cut).where("v_sg <> u_sg").join(ends, ["v", "u"], "left_anti").select("v", "w", "u")


def per_vertex(tri: DataFrame) -> DataFrame:
    return tri.select(F.explode(F.array(*NAMES)).alias("vid")).groupBy("vid").agg(F.count("*").alias("triangles"))


def clustering_coefficient(g: PartitionedGraph) -> DataFrame:
    """(vid, degree, triangles, coefficient) of vertices with at least two neighbours."""
    d = degrees(g).where("degree > 1")
    got = d.join(per_vertex(triangles(g)), "vid", "left").withColumn("triangles", F.coalesce("triangles", F.lit(0)))
    return got.withColumn("coefficient", F.round(2.0 * F.col("triangles") / (F.col("degree") * (F.col("degree") - 1)), 6))


def per_edge(tri: DataFrame) -> DataFrame:
    """(src, dst, triangles) of the edges in a triangle."""
    sides = F.array(*[F.struct(F.col(x).alias("src"), F.col(y).alias("dst")) for x, y in ("ab", "ac", "bc")])
    return tri.select(F.explode(sides).alias("e")).groupBy("e.src", "e.dst").agg(F.count("*").alias("triangles"))


#: In decimals: three million times the triangles of a large graph is beyond a bigint.
_MILLIONTHS = "case when wedges > 0 then cast(3000000 * cast(triangles as decimal(28, 0)) div wedges as bigint) end transitivity"


def transitivity(g: PartitionedGraph) -> DataFrame:
    """(triangles, wedges, transitivity): closed wedges among all, in millionths (whole numbers, so engines agree)."""
    wedges = degrees(g).agg(F.coalesce(F.sum(F.expr("degree * (degree - 1) div 2")), F.lit(0)).alias("wedges"))
    tri = _total(g.edges, "degree")
    return tri.crossJoin(wedges).select("triangles", "wedges", F.expr(_MILLIONTHS))


def transitivity_of_sets(members: DataFrame) -> DataFrame:
    """(triangles, wedges, transitivity) of the graph in which vertices are joined that share an item, from members (vid, item).

    Vertices with one set of items have the same neighbours and each other: they count as one vertex with a weight, and no
    pair of them is formed. Exact for any sets; with all sets unlike it is the plain count.
    """
    sets = members.where("vid is not null and item is not null").groupBy("vid").agg(F.sort_array(F.collect_set("item")).alias("items"))
    alike = sets.groupBy("items").agg(F.count("*").alias("weight")).select(F.monotonically_increasing_id().alias("vid"), F.lit(0).alias("sg"), "weight", "items")
    alike = spill(alike)
    has = alike.select("vid", "weight", F.explode("items").alias("item"))
    met = has.alias("x").join(has.alias("y"), F.expr("x.item = y.item and x.vid < y.vid"))
    pairs = spill(met.select(*[F.col(c).alias(n) for c, n in (("x.vid", "src"), ("y.vid", "dst"), ("x.weight", "ws"), ("y.weight", "wd"))]).distinct())
    zero = lambda e, n: F.coalesce(F.sum(F.expr(e)), F.lit(0)).alias(n)
    near = pairs.select(F.col("src").alias("vid"), F.col("wd").alias("w")).union(pairs.select("dst", "ws")).groupBy("vid").agg(F.sum("w").alias("near"))
    k = "cast(weight as decimal(12, 0))"
    degree = alike.join(near, "vid", "left").withColumn("degree", F.col("weight") - 1 + F.coalesce("near", F.lit(0)))
    own = degree.agg(zero("weight * (degree * (degree - 1) div 2)", "wedges"), zero(f"{k} * ({k} - 1) * ({k} - 2) / 6", "own"))
    two = pairs.agg(zero("(ws * (ws - 1) div 2) * wd + ws * (wd * (wd - 1) div 2)", "two"))
    three = in_cells(pairs.select("src", "dst"), True, vertices=alike.select("vid", "sg", "weight")).agg(zero("triangles", "three"))
    found = own.crossJoin(two).crossJoin(three).select(F.expr("cast(own + two + three as bigint)").alias("triangles"), F.col("wedges").cast("bigint"))
    return found.select("triangles", "wedges", F.expr(_MILLIONTHS))


def owned_sets(members: DataFrame) -> DataFrame:
    """(vid, sg, items) of members (vid, sg, item): the items of each vertex. Rows with a null vertex or item play no part."""
    return members.where("vid is not null and item is not null").groupBy("vid", "sg").agg(F.sort_array(F.collect_set("item")).alias("items"))


def set_classes(sets: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Classes (vid, sg, weight, items) of sets (vid, sg, items), and the pairs (src, dst) of classes that share an item.

    Vertices of one owner with one set of items have the same neighbours and each other: a class stands for ``weight`` of
    them. The owner null is one class here.
    """
    alike = spill(sets.groupBy("items", "sg").agg(F.count("*").alias("weight")).select(F.monotonically_increasing_id().alias("vid"), "sg", "weight", "items"))
    has = alike.select(F.col("vid").alias("member"), F.explode("items").alias("item"))
    numbered = spill(has.select("item").distinct().withColumn("k", F.monotonically_increasing_id()))
    pairs = met_pairs(has.join(numbered, "item").select("k", "member")).select("src", "dst")
    return alike, spill(pairs, numbered)


#: Members of a class that are set in at once (Spark holds all rows made of one: 32768 here), and triangles that a task lists,
#: about.
LISTED_BLOCK, LISTED_TASK = 32, 8_000_000


def triangles_of_sets(g: PartitionedGraph, members: DataFrame, form: Callable[[PartitionedGraph], DataFrame]) -> DataFrame:
    """(a, b, c, tri_type) of ``g``, in which vertices are joined that share an item, from members (vid, item).

    ``form`` finds the triangles of classes of vertices with one owner and one set of items; their members are set in block
    by block where the rows are read, so that listed triangles are neither shuffled nor sent to Python. Where most vertices
    are unlike, ``form`` lists the triangles of ``g`` itself.
    """
    sets = spill(owned_sets(members.withColumn("sg", F.lit(0))).drop("sg").join(g.vertices.select("vid", "sg"), "vid"))
    classes, pairs = set_classes(sets)
    if 2 * classes.count() > sets.count():
        return form(g)
    end = lambda v, sg: classes.select(F.col("vid").alias(v), F.col("sg").alias(sg))
    three = form(PartitionedGraph(classes.select("vid", "sg"), pairs.withColumn("weight", F.lit(1).cast("bigint")))).toDF("p", "q", "r", "tri_type")
    sides = pairs.join(end("src", "s"), "src").join(end("dst", "d"), "dst")
    typed = lambda own: F.when(F.col("s") == F.col("d"), "i").when(F.col(own).isNotNull(), "ii").otherwise("iii")
    two = sides.select("src", "src", "dst", typed("s")).union(sides.select("src", "dst", "dst", typed("d")))
    one = classes.where("weight > 2").select("vid", "vid", "vid", F.when(F.col("sg").isNotNull(), "i").otherwise("iii"))
    met = spill(three.union(two).union(one))
    nth = F.row_number().over(Window.partitionBy("cls").orderBy("vid")) - 1
    named = classes.select(F.col("vid").alias("cls"), F.col("sg").alias("own"), F.col("items").alias("held"))
    ranked = sets.join(named, F.col("items").eqNullSafe(F.col("held")) & F.col("sg").eqNullSafe(F.col("own"))).select("cls", "vid").withColumn("block", F.floor(nth / LISTED_BLOCK))
    blocks = spill(ranked.groupBy("cls", "block").agg(F.collect_list("vid").alias("vids")))
    # (p, i): the i-th block of class p; a class that is repeated gives each pair of its blocks once
    sizes = blocks.select("cls", "block", F.size("vids").alias("n"))
    dealt = met
    for c, k in zip("pqr", "ijk", strict=True):
        dealt = dealt.join(F.broadcast(sizes.toDF(c, k, f"n{k}")), c)
    dealt = dealt.where("(p <> q or i <= j) and (q <> r or j <= k)")
    rows = dealt.agg(F.sum(F.expr("cast(ni as double) * nj * nk"))).first()[0] or 0
    dealt = dealt.select(*"piqjrk", "tri_type").repartition(max(1, min(20_000, math.ceil(rows / LISTED_TASK))))
    for c, k, v in zip("pqr", "ijk", "xyz", strict=True):
        dealt = dealt.join(F.broadcast(blocks.toDF(c, k, f"{v}s")), [c, k])
    listed = dealt.select("p", "q", "r", "tri_type", "ys", "zs", F.explode("xs").alias("x"))
    listed = listed.select("p", "q", "r", "tri_type", "zs", "x", F.explode("ys").alias("y")).where("p <> q or x < y")
    listed = listed.select("q", "r", "tri_type", F.least("x", "y").alias("x"), F.greatest("x", "y").alias("y"), F.col("y").alias("last"), F.explode("zs").alias("z")).where("q <> r or last < z")
    found = listed.select(F.least("x", "z").alias("a"), F.greatest("x", F.least("y", "z")).alias("b"), F.greatest("y", "z").alias("c"), "tri_type")
    return found.where("a < b and b < c")


def count_of_classes(classes: DataFrame, pairs: DataFrame) -> DataFrame:
    """(own, triangles) where all that meet have one owner: within a class, over two classes and over three."""
    k = "cast(weight as decimal(12, 0))"
    one = classes.select(F.col("sg").alias("own"), F.expr(f"({k} * ({k} - 1) * ({k} - 2)) div 6").alias("triangles"))
    ends = [classes.select(F.col("vid").alias(n), F.col("weight").alias(w), *own) for n, w, own in (("src", "ws", [F.col("sg").alias("own")]), ("dst", "wd", []))]
    two = pairs.join(ends[0], "src").join(ends[1], "dst").select("own", F.expr("(ws * (ws - 1) div 2) * wd + ws * (wd * (wd - 1) div 2)").alias("triangles"))
    three = in_cells(pairs, True, vertices=classes.select("vid", "sg", "weight")).select("own", "triangles")
    return one.unionByName(two).unionByName(three).groupBy("own").agg(F.sum("triangles").alias("triangles")).where("triangles > 0")


def classify(tri: DataFrame, vertices: DataFrame) -> DataFrame:
    """(a, b, c, tri_type, away): the number of subgraphs, and for type ii which vertex is alone."""
    for n in NAMES:
        tri = tri.join(vertices.select(F.col("vid").alias(n), F.col("sg").alias(f"{n}_sg")), n)
    ab, bc, ac = (F.col(f"{x}_sg") == F.col(f"{y}_sg") for x, y in ("ab", "bc", "ac"))
    kind = F.when(ab & bc, "i").when(ab | bc | ac, "ii").otherwise("iii")
    away = F.when(ab & bc, None).when(bc, "first").when(ac, "middle").when(ab, "last")
    return tri.select(*NAMES, kind.alias("tri_type"), away.alias("away"))


def type2_placement(g: PartitionedGraph) -> DataFrame:
    """(away, triangles) of type ii: ``first`` are those that the printed program misses."""
    found = _owned_cells(g, True).where("kind not in ('i', 'iii')")
    return found.groupBy(F.col("kind").alias("away")).agg(F.sum("triangles").alias("triangles"))


def triangle_recall(g: PartitionedGraph) -> DataFrame:
    """(found, total, missed) of the printed program against all triangles."""
    kinds = classify(triangles_forward(g), g.vertices).agg(F.count_if(F.col("away") == "first").alias("missed"), F.count("*").alias("total"))
    printed = triangles_bsp(g, "as_printed")[0].agg(F.count("*").alias("found"))
    return printed.crossJoin(kinds).select("found", "total", "missed")


def orient(g: PartitionedGraph, by: str = "id") -> DataFrame:
    """(lo, hi): each edge once, towards the larger id or the larger (degree, id)."""
    if by == "id":
        return g.edges.select(F.col("src").alias("lo"), F.col("dst").alias("hi"))
    d = degrees(g)
    e = g.edges.join(d.select(F.col("vid").alias("src"), F.col("degree").alias("ds")), "src").join(d.select(F.col("vid").alias("dst"), F.col("degree").alias("dd")), "dst")
    up = F.struct("ds", "src") < F.struct("dd", "dst")
    return e.select(F.when(up, F.col("src")).otherwise(F.col("dst")).alias("lo"), F.when(up, F.col("dst")).otherwise(F.col("src")).alias("hi"))


def probes(g: PartitionedGraph) -> DataFrame:
    """(form, probes): pairs of neighbours that each form tests for a closing edge."""
    by_id = orient(g).groupBy("lo").agg(F.count("*").alias("o"))
    by_degree = orient(g, "degree").groupBy("lo").agg(F.count("*").alias("o"))
    pairs = F.coalesce(F.sum(F.expr("o * (o - 1) div 2")), F.lit(0)).alias("probes")
    own = g.owned_edges().where("src_sg = dst_sg")
    deg = degrees(g)
    ends = own.join(deg.select(F.col("vid").alias("src"), F.col("degree").alias("ds")), "src").join(deg.select(F.col("vid").alias("dst"), F.col("degree").alias("dd")), "dst")
    local = ends.agg(F.coalesce(F.sum(F.least("ds", "dd")), F.lit(0)).alias("probes"))
    named = lambda df, form: df.select(F.lit(form).alias("form"), "probes")
    return named(by_id.agg(pairs), "node_iterator").unionByName(named(by_degree.agg(pairs), "forward")).unionByName(named(local, "subgraph_kernel"))


def triangles_colour(g: PartitionedGraph, colours: int = 3) -> DataFrame:
    """(a, b, c) by colour triples: vertices are hashed to colours, an edge goes to each triple that holds both its
    colours, and a triangle is kept in the triple of exactly its colours."""
    from .partitions import hash_part

    e = g.edges.select("src", "dst", hash_part(F.col("src"), colours).alias("i"), hash_part(F.col("dst"), colours).alias("j"))
    other = F.explode(F.sequence(F.lit(0), F.lit(colours - 1)))
    dealt = e.withColumn("k", other).select("src", "dst", F.array_join(F.array_sort(F.array("i", "j", "k")), "-").alias("triple")).distinct()
    x, y = dealt.select("triple", F.col("src").alias("a"), F.col("dst").alias("b")), dealt.select("triple", F.col("src").alias("b"), F.col("dst").alias("c"))
    near = x.join(y, ["triple", "b"]).join(dealt.select("triple", F.col("src").alias("a"), F.col("dst").alias("c")), ["triple", "a", "c"], "left_semi")
    exact = F.array_join(F.array_sort(F.array(*[hash_part(F.col(n), colours) for n in NAMES])), "-")
    return near.where(F.col("triple") == exact).select(*NAMES)


def triangles_estimate(g: PartitionedGraph, percent: int = 50, seed: int = 7) -> DataFrame:
    """(kept_edges, kept_triangles, estimate): triangles among a hash sample of the edges, scaled by the cube."""
    from .partitions import hash_part

    kept = g.edges.where(hash_part(F.concat_ws(":", F.lit(seed), "src", "dst"), 100) < percent)
    sample = PartitionedGraph(g.vertices, kept)
    tri = triangles_forward(sample).agg(F.count("*").alias("kept_triangles"))
    n = kept.agg(F.count("*").alias("kept_edges"))
    return n.crossJoin(tri).select("kept_edges", "kept_triangles", F.expr(f"kept_triangles * 1000000 div {percent ** 3}").alias("estimate"))


def k_truss(g: PartitionedGraph, k: int, max_rounds: int = 1000) -> DataFrame:
    """(src, dst): the largest set of edges each of which is in k - 2 triangles of the set, by repeated peeling."""
    edges = spill(g.edges.select("src", "dst", "weight"))
    n = edges.count()
    for _ in range(max_rounds):
        support = per_edge(triangles_forward(PartitionedGraph(g.vertices, edges)))
        edges = spill(edges.join(support.where(F.col("triangles") >= k - 2).select("src", "dst"), ["src", "dst"], "left_semi"), edges)
        left = edges.count()
        if left == n:
            return edges.select("src", "dst")
        n = left
    raise RuntimeError(f"edges still leave after {max_rounds} rounds")


def triangles_vertex_supersteps(g: PartitionedGraph) -> list[dict]:
    """The baseline's log: always three supersteps, whatever a round sends."""
    e = g.edges.select("src", "dst")
    asked = e.select(F.col("src").alias("v"), F.col("dst").alias("w"))
    second = spill(asked.join(e.select(F.col("src").alias("w"), F.col("dst").alias("u")), "w"))
    return [{"superstep": 0, "found": 0, "messages": e.count()}, {"superstep": 1, "found": 0, "messages": second.count()}, {"superstep": 2, "found": _closed(second, e).count(), "messages": 0}]
