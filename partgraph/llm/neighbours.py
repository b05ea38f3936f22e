"""Approximate nearest neighbours by largest inner product: an NN-descent graph and greedy search on it.

Vectors get one more coordinate so that all have the length of the longest: the largest inner product is then the least
distance. Vectors travel as float32; that coordinate and the scores of the graph are taken in double precision from them,
so that one long vector does not blur the others. Random hyperplanes through the middle of a sample deal the rows into
blocks whose best pairs start the graph. Each round joins the graph with itself: the neighbours and reverse neighbours of
a node meet at the node, pairs of two edges that met before are passed over, and meetings better than a row's worst edge
replace it. Rounds go on until at most DELTA of the edges are new.

Nodes that hyperplanes put together share a cell of about CELL rows. Whatever a round or a search step needs of vectors is
sent to a cell once, not once for each of its nodes.

Queries start at their own row's neighbours; each step opens the best unopened nodes of every query and joins their
neighbours, until no query has an unopened node among its BEAM best. Final scores are exact, in double precision on the
original vectors.

Cases: null, zero or non-finite vectors and vectors holding nulls take no part, nor do those of another length than most
(of lengths equally frequent, the least); of rows with one vec_id the least vector stays; null vec_ids take no part; ties
go to the smaller vec_id; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import forget, lists_of, partitions, spill, whole_groups

TOP = 20
DEGREE = 32
#: Rounds end when at most this share of the edges is new.
DELTA = 0.02
TREES = 6
BLOCK = 400
CELL = 4096
#: Rows that tell where the middle of each hyperplane lies.
SAMPLE = 4096
BEAM, OPEN = 96, 24


def sound_vectors(table: DataFrame) -> DataFrame:
    """(id, v): the vectors that take part, as doubles."""
    v = F.col("embedding").cast("array<double>")
    bad = F.exists("v", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == F.lit(float("inf"))))
    rows = table.select(F.col("vec_id").cast("bigint").alias("id"), v.alias("v")).where("id is not null and v is not null")
    rows = rows.where(~F.coalesce(bad, F.lit(True)) & F.exists("v", lambda x: x != 0))
    usual = rows.groupBy(F.size("v").alias("n")).agg(F.count("*").alias("rows")).orderBy(F.desc("rows"), "n").first()
    return rows.where(F.size("v") == (usual["n"] if usual else 0)).groupBy("id").agg(F.min("v").alias("v"))


def _matrix(column) -> np.ndarray:
    chunk = column.combine_chunks() if hasattr(column, "combine_chunks") else column
    return np.asarray(chunk.flatten()).reshape(len(chunk), -1)


def _levelled(vectors: DataFrame) -> DataFrame:
    """(id, x): float vectors, the longest of length 1; scaled by the largest component first, so that no square overflows."""
    top = F.lit(vectors.agg(F.max(F.array_max(F.transform("v", F.abs)))).first()[0] or 1.0)
    square = F.aggregate("v", F.lit(0.0), lambda a, x: a + (x / top) * (x / top))
    most = F.lit(vectors.agg(F.max(square)).first()[0] or 1.0)
    return vectors.select("id", F.transform("v", lambda x: (x / top / F.sqrt(most)).cast("float")).alias("x"))


def _scores(x: np.ndarray) -> np.ndarray:
    """Inner products of all pairs of rows once each has the coordinate that makes it of length 1; -inf with itself."""
    x = x.astype(np.float64)
    last = np.sqrt(np.maximum(1 - (x * x).sum(1), 0))
    s = x @ x.T + np.outer(last, last)
    np.fill_diagonal(s, -np.inf)
    return s


def _first_of(table_u: np.ndarray, v: np.ndarray, s: np.ndarray, fresh: np.ndarray, k: int) -> np.ndarray:
    """Places of the k best distinct v of each u; of a repeated (u, v) one that is not fresh, then the best, stays."""
    order = np.lexsort((-s, fresh, v, table_u))
    u, w = table_u[order], v[order]
    head = np.ones(len(u), bool)
    head[1:] = (u[1:] != u[:-1]) | (w[1:] != w[:-1])
    order = order[head]
    order = order[np.lexsort((v[order], -s[order], table_u[order]))]
    u = table_u[order]
    start = np.flatnonzero(np.concatenate([[True], u[1:] != u[:-1]])) if len(u) else np.zeros(0, np.int64)
    turn = np.arange(len(u)) - np.repeat(start, np.diff(np.append(start, len(u))))
    return order[turn < k]


EDGE = "u bigint, v bigint, s double, fresh boolean"


def _best(edges: DataFrame, k: int) -> DataFrame:
    """The k best (u, v, s, fresh) of each u."""
    import pyarrow as pa

    def run(batches):
        for table, _ in whole_groups(batches, ["u"], rows=100_000):
            u, v, s, fresh = (np.asarray(table.column(c)) for c in ("u", "v", "s", "fresh"))
            keep = _first_of(u, v, s, fresh, k)
            yield pa.RecordBatch.from_arrays([pa.array(c[keep]) for c in (u, v, s, fresh)], ["u", "v", "s", "fresh"])

    return edges.select("u", "v", "s", "fresh").repartition("u").sortWithinPartitions("u").mapInArrow(run, EDGE)


def _planes(level: DataFrame, count: int, dim: int, bits: int, trees: int, seed: int):
    """Hyperplanes of each tree, and where their middles lie in a sample of rows."""
    planes = [np.random.default_rng(seed + t).normal(size=(dim, bits)) for t in range(trees)]
    some = _matrix(level.orderBy(F.xxhash64("id", F.lit(5))).limit(SAMPLE).select("x").toArrow().column("x")) if bits else np.zeros((1, dim))
    return planes, [np.median(some @ p, axis=0) for p in planes]


def _coded(level: DataFrame, size: int, trees: int, seed: int) -> DataFrame:
    """(id, x, key, part): every row in one block of each tree; blocks above ``size`` rows are dealt on."""
    import pyarrow as pa

    first = level.agg(F.count("*"), F.max(F.size("x"))).first()
    count, dim = first[0], first[1] or 1
    bits = max(0, int(np.ceil(np.log2(max(1, count / size)))))
    planes, middle = _planes(level, count, dim, bits, trees, seed)

    def code(batches):
        for batch in batches:
            x = _matrix(batch.column("x"))
            keys = [(x @ planes[t] > middle[t]).astype(np.int64) @ (1 << np.arange(bits, dtype=np.int64)) * trees + t if len(x) else np.zeros(0, np.int64) for t in range(trees)]
            take = pa.array(np.tile(np.arange(len(x)), trees))
            yield pa.RecordBatch.from_arrays([batch.column("id").take(take), batch.column("x").take(take), pa.array(np.concatenate(keys))], ["id", "x", "key"])

    coded = level.select("id", "x").mapInArrow(code, "id bigint, x array<float>, key bigint")
    sizes = coded.groupBy("key").agg(F.ceil(F.count("*") / size).cast("int").alias("split"))
    return coded.join(sizes, "key").select("id", "x", "key", F.pmod(F.xxhash64("id", "key"), F.col("split")).alias("part"))


def with_cells(level: DataFrame) -> DataFrame:
    """(id, x, cell)."""
    return _coded(level, CELL, 1, 50).select("id", "x", F.xxhash64("key", "part").alias("cell"))


def _first_graph(level: DataFrame) -> DataFrame:
    """Edges between rows of one block of each random partition."""
    import pyarrow as pa

    def block(table: pa.Table) -> pa.Table:
        ids, x = np.asarray(table.column("id")), _matrix(table.column("x"))
        s = _scores(x)
        k = min(DEGREE, len(ids) - 1)
        if k < 1:
            return pa.table({"u": pa.array([], pa.int64()), "v": pa.array([], pa.int64()), "s": pa.array([], pa.float64()), "fresh": pa.array([], pa.bool_())})
        near = np.argpartition(-s, k - 1, axis=1)[:, :k]
        return pa.table({"u": np.repeat(ids, k), "v": ids[near].ravel(), "s": np.take_along_axis(s, near, 1).ravel(), "fresh": np.ones(near.size, bool)})

    return _best(_coded(level, BLOCK, TREES, 100).groupBy("key", "part").applyInArrow(block, EDGE), DEGREE)


def _descend(graph: DataFrame, placed: DataFrame) -> DataFrame:
    """One round: neighbours and reverse neighbours of each node meet; the best edges stay, ``fresh`` if they are new."""
    import pyarrow as pa

    back = _best(graph.select(F.col("v").alias("u"), F.col("u").alias("v"), "s", "fresh"), DEGREE)
    members = graph.unionByName(back).groupBy("u", "v").agg(F.max("fresh").alias("fresh"))
    members = members.join(members.where("fresh").select("u").distinct(), "u", "left_semi")
    worst = graph.groupBy(F.col("u").alias("id")).agg(F.min("s").alias("low"), F.count("*").alias("n"))
    known = placed.join(worst, "id", "left").select(F.col("id").alias("v"), "x", F.when(F.col("n") >= DEGREE, F.col("low")).otherwise(F.lit(-2.0)).alias("low"))
    dealt = members.join(placed.select(F.col("id").alias("u"), "cell"), "u")
    needed = dealt.select("cell", "v").distinct().join(known, "v").select(F.col("cell").alias("at"), F.col("v").alias("node"), "x", "low")

    def meet(asked: pa.Table, have: pa.Table) -> pa.Table:
        ids, x, low = np.asarray(have.column("node")), _matrix(have.column("x")), np.asarray(have.column("low"))
        order = np.argsort(ids)
        u, v, fresh = (np.asarray(asked.column(c)) for c in ("u", "v", "fresh"))
        by = np.argsort(u, kind="stable")
        u, fresh, place = u[by], fresh[by], order[np.searchsorted(ids, v[by], sorter=order)]
        edges = np.append(np.flatnonzero(np.concatenate([[True], u[1:] != u[:-1]])), len(u))
        out: list[list[np.ndarray]] = [[], [], []]
        for a, b in zip(edges[:-1], edges[1:], strict=True):
            k = min(DEGREE, b - a - 1)
            if k < 1:
                continue
            at, new = place[a:b], fresh[a:b]
            s = _scores(x[at])
            s[~(new[:, None] | new[None, :]) | (s <= low[at][:, None])] = -np.inf
            near = np.argpartition(-s, k - 1, axis=1)[:, :k]  # a row keeps DEGREE edges, so no node gives it more
            best = np.take_along_axis(s, near, 1)
            i, j = np.nonzero(best > -np.inf)
            for o, y in zip(out, (at[i], at[near[i, j]], best[i, j]), strict=True):
                o.append(y)
        a, b, s = (np.concatenate(o) if o else np.zeros(0) for o in out)
        a, b = ids[a.astype(np.int64)], ids[b.astype(np.int64)]
        keep = _first_of(a, b, s, np.ones(len(a), bool), DEGREE)
        return pa.table({"u": a[keep], "v": b[keep], "s": s[keep], "fresh": np.ones(len(keep), bool)})

    found = dealt.groupBy("cell").cogroup(needed.groupBy("at")).applyInArrow(meet, EDGE)
    return _best(found.unionByName(graph.withColumn("fresh", F.lit(False))), DEGREE)


def neighbour_graph(level: DataFrame, delta: float = DELTA) -> DataFrame:
    """(u, v, s, fresh): about the DEGREE nearest rows of each row; ``level`` may hold cells already."""
    placed = level if "cell" in level.columns else spill(with_cells(level))
    graph = spill(_first_graph(placed))
    while True:
        graph = spill(_descend(graph, placed), graph)
        new, edges = graph.agg(F.count_if("fresh"), F.count("*")).first()
        if new <= delta * edges:
            return graph


def _scored(pairs: DataFrame, points: DataFrame, queries: DataFrame) -> DataFrame:
    """(q, v, s): inner products of (q, v) pairs, taken in the cells of v; points (id, v, cell), queries (id, v)."""
    import pyarrow as pa

    dealt = pairs.join(points.select(F.col("id").alias("v"), "cell"), "v").select("cell", "q", "v")
    here = dealt.select("cell", "v").distinct().join(points.select(F.col("id").alias("v"), F.col("v").alias("x")), "v").select(F.col("cell").alias("at"), F.lit(False).alias("asks"), F.col("v").alias("id"), "x")
    asks = dealt.select("cell", "q").distinct().join(queries.select(F.col("id").alias("q"), F.col("v").alias("x")), "q").select(F.col("cell").alias("at"), F.lit(True).alias("asks"), F.col("q").alias("id"), "x")

    def score(asked: pa.Table, have: pa.Table) -> pa.Table:
        flag, ids, (flat, edges) = np.asarray(have.column("asks")), np.asarray(have.column("id")), lists_of(have.column("x"))
        x = flat.reshape(len(ids), -1) if len(ids) else flat.reshape(0, 1)
        places = []
        for names, side in ((asked.column("q"), flag), (asked.column("v"), ~flag)):
            mine = np.flatnonzero(side)
            mine = mine[np.argsort(ids[mine])]
            places.append(mine[np.searchsorted(ids[mine], np.asarray(names))])
        s = np.empty(len(asked))
        for a in range(0, len(s), 1 << 16):
            s[a : a + (1 << 16)] = np.einsum("ij,ij->i", x[places[0][a : a + (1 << 16)]], x[places[1][a : a + (1 << 16)]])
        return pa.table({"q": asked.column("q"), "v": asked.column("v"), "s": s})

    return dealt.groupBy("cell").cogroup(here.unionByName(asks).groupBy("at")).applyInArrow(score, "q bigint, v bigint, s double")


BEAMS = "q bigint, v bigint, s double, open boolean, now boolean"


def _turn(beam: DataFrame) -> DataFrame:
    """The BEAM best of each query, ``now`` for the OPEN best of them that are still open."""
    import pyarrow as pa

    def run(batches):
        for table, _ in whole_groups(batches, ["q"], rows=100_000):
            q, v, s, open_ = (np.asarray(table.column(c)) for c in ("q", "v", "s", "open"))
            keep = _first_of(q, v, s, open_, BEAM)
            q, v, s, open_ = q[keep], v[keep], s[keep], open_[keep]
            turn = np.cumsum(open_)
            first = np.searchsorted(q, q) if len(q) and (np.diff(q) >= 0).all() else np.zeros(len(q), np.int64)
            before = np.concatenate([[0], turn])[first]
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in (q, v, s, open_, open_ & (turn - before <= OPEN))], ["q", "v", "s", "open", "now"])

    return beam.select("q", "v", "s", "open").repartition("q").sortWithinPartitions("q").mapInArrow(run, BEAMS)


def search(graph: DataFrame, points: DataFrame, queries: DataFrame, top: int = TOP) -> DataFrame:
    """(query_id, rank, vec_id, score) by greedy search from each query's own row; ``queries`` holds (id, v)."""
    both = graph.select("u", "v", "s", F.lit(False).alias("fresh"))
    both = both.unionByName(both.select(F.col("v").alias("u"), F.col("u").alias("v"), "s", "fresh"))
    hops = spill(_best(both, 2 * DEGREE).select("u", "v"))
    start = queries.select(F.col("id").alias("q")).join(hops, F.col("q") == F.col("u")).select("q", "v")
    beam = _scored(start.distinct(), points, queries).withColumn("open", F.lit(True))
    held = None
    while True:
        held = spill(_turn(beam), held) if held is not None else spill(_turn(beam))
        now = held.where("now")
        if now.isEmpty():
            break
        reached = now.select("q", F.col("v").alias("u")).join(hops, "u").select("q", "v").where("q <> v").distinct()
        fresh = _scored(reached.join(held.select("q", "v"), ["q", "v"], "left_anti"), points, queries).withColumn("open", F.lit(True))
        beam = held.select("q", "v", "s", (F.col("open") & ~F.col("now")).alias("open")).unionByName(fresh)
    forget(hops)
    return _exact(held.select("q", "v"), points, queries, top)


def _exact(pairs: DataFrame, points: DataFrame, queries: DataFrame, top: int) -> DataFrame:
    """The ``top`` best of each query's few pairs, by products summed in order in double precision."""
    dot = F.aggregate(F.zip_with("qv", "pv", lambda a, b: a * b), F.lit(0.0), lambda a, x: a + x)
    met = pairs.join(points.select(F.col("id").alias("v"), F.col("v").alias("pv")), "v").join(queries.select(F.col("id").alias("q"), F.col("v").alias("qv")), "q")
    w = Window.partitionBy("q").orderBy(F.desc("s"), "v")
    ranked = met.select("q", "v", dot.alias("s")).withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= top)
    return ranked.select(F.col("q").alias("query_id"), "rank", F.col("v").alias("vec_id"), F.col("s").alias("score"))


def complete(found: DataFrame, points: DataFrame, queries: DataFrame, top: int = TOP) -> DataFrame:
    """Queries that the graph gave fewer than ``top`` rows (small or split tables) get theirs from all rows, cell by cell."""
    import pyarrow as pa

    have = found.groupBy("query_id").agg(F.count("*").alias("n"))
    goal = min(top, max(0, points.count() - 1))
    short = queries.join(have, F.col("id") == F.col("query_id"), "left").where(F.coalesce("n", F.lit(0)) < goal).select("id", "v")
    if short.isEmpty():
        return found
    sent = short.select(F.col("id").alias("asker"), F.col("v").alias("y")).crossJoin(points.select(F.col("cell").alias("at")).distinct())

    def best(cell: pa.Table, asks: pa.Table) -> pa.Table:
        ids, q = np.asarray(cell.column("id")), np.asarray(asks.column("asker"))
        if not len(ids) or not len(q):
            return pa.table({"q": pa.array([], pa.int64()), "v": pa.array([], pa.int64())})
        x, y = _matrix(cell.column("v")), _matrix(asks.column("y"))
        out: list[list[np.ndarray]] = [[], []]
        for i in range(len(q)):
            s = x @ y[i]
            s[ids == q[i]] = -np.inf
            # ties at the border of the list come along
            last = np.sort(s)[-min(top, len(s))]
            near = np.flatnonzero((s >= last - abs(last) * 1e-9) & (s > -np.inf))
            out[0].append(np.full(len(near), q[i]))
            out[1].append(ids[near])
        return pa.table({"q": np.concatenate(out[0]), "v": np.concatenate(out[1])})

    pairs = points.groupBy("cell").cogroup(sent.groupBy("at")).applyInArrow(best, "q bigint, v bigint")
    return found.join(short, F.col("query_id") == F.col("id"), "left_anti").unionByName(_exact(pairs, points, queries, top))


def op9_nn_descent(spark, sf_dir: str) -> DataFrame:
    vectors = spill(sound_vectors(spark.read.parquet(f"{sf_dir}/embeddings.parquet")).repartition(partitions(spark), "id"))
    placed = spill(with_cells(_levelled(vectors)))
    graph = neighbour_graph(placed)
    points = spill(vectors.join(placed.select("id", "cell"), "id"), placed)
    queries = points.where(F.col("id") % 20 == 0).select("id", "v")
    found = spill(search(graph, points, queries))
    forget(graph, vectors)
    return complete(found, points, queries)
