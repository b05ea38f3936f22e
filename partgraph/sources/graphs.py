"""Graphs derived from the given tables: canonical edges (src < dst, unique) and vertices with their partition."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..storage import spill


@dataclass(frozen=True)
class PartitionedGraph:
    """``vertices`` (vid, sg) and ``edges`` (src, dst, weight), src < dst, each pair once; ``owned``: edges with the owners
    of their ends, where these are stored."""

    vertices: DataFrame
    edges: DataFrame
    owned: DataFrame | None = None

    def with_partition(self, sg) -> PartitionedGraph:
        """The same graph under another owner of each vertex, given as a column of ``vid``."""
        return PartitionedGraph(self.vertices.select("vid", sg.cast("bigint").alias("sg")), self.edges)

    def owned_edges(self) -> DataFrame:
        """(src, dst, weight, src_sg, dst_sg)."""
        if self.owned is not None:
            return self.owned
        v = self.vertices
        a, b = v.select(F.col("vid").alias("src"), F.col("sg").alias("src_sg")), v.select(F.col("vid").alias("dst"), F.col("sg").alias("dst_sg"))
        return self.edges.join(a, "src").join(b, "dst").select("src", "dst", "weight", "src_sg", "dst_sg")

    def stored(self) -> PartitionedGraph:
        """The same graph written once to the shared folder, edges with their owners, as a partitioner leaves it."""
        vertices, edges = spill(self.vertices.select("vid", "sg")), spill(self.edges.select("src", "dst", "weight"))
        owned = spill(PartitionedGraph(vertices, edges).owned_edges(), edges)
        return PartitionedGraph(vertices, owned.select("src", "dst", "weight"), owned)

    def half_edges(self) -> DataFrame:
        """(u, v, weight): both directions."""
        e = self.edges
        return e.select(F.col("src").alias("u"), F.col("dst").alias("v"), "weight").union(e.select("dst", "src", "weight"))


def symmetrize(arrows: DataFrame) -> DataFrame:
    """Undirected simple edges of directed, repeated or looping ones; of parallel edges the least weight stays."""
    pairs = arrows.where("src <> dst").select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), "weight")
    return pairs.groupBy("src", "dst").agg(F.min("weight").alias("weight"))


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _brand(df: DataFrame) -> DataFrame:
    return df.select(F.col("p_partkey").alias("vid"), F.regexp_extract("p_brand", r"(\d+)$", 1).cast("bigint").alias("sg"))


def copart(spark: SparkSession, sf_dir: str, support: int = 1) -> PartitionedGraph:
    """Parts met in one order at least ``support`` times; weight is the price distance; owner is the brand."""
    lines = _table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    pairs = lines.alias("x").join(lines.alias("y"), F.expr("x.l_orderkey = y.l_orderkey and x.l_partkey < y.l_partkey"))
    met = pairs.groupBy(F.col("x.l_partkey").alias("src"), F.col("y.l_partkey").alias("dst")).agg(F.count("*").alias("n")).where(F.col("n") >= support)
    part = _table(spark, sf_dir, "part")
    price = part.select("p_partkey", F.round(F.col("p_retailprice") * 100).cast("bigint").alias("cents"))
    a, b = price.select(F.col("p_partkey").alias("src"), F.col("cents").alias("ca")), price.select(F.col("p_partkey").alias("dst"), F.col("cents").alias("cb"))
    return PartitionedGraph(_brand(part), met.join(a, "src").join(b, "dst").select("src", "dst", F.abs(F.col("ca") - F.col("cb")).alias("weight")))


def copart_strong(spark: SparkSession, sf_dir: str) -> PartitionedGraph:
    return copart(spark, sf_dir, 2)


def nation_trade(spark: SparkSession, sf_dir: str) -> PartitionedGraph:
    """Nations whose customers buy from the other's suppliers; owner is the region."""
    line = _table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey")
    cust = _table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("o_custkey"), F.col("c_nationkey").cast("bigint").alias("cn"))
    supp = _table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), F.col("s_nationkey").cast("bigint").alias("sn"))
    orders = _table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey").join(cust, "o_custkey")
    met = line.join(orders, "l_orderkey").join(supp, "l_suppkey").where("cn <> sn").groupBy(F.least("cn", "sn").alias("src"), F.greatest("cn", "sn").alias("dst")).agg(F.count("*").alias("n"))
    nation = _table(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("bigint").alias("vid"), F.col("n_regionkey").cast("bigint").alias("sg"))
    return PartitionedGraph(nation, met.select("src", "dst", F.expr("1000000 div n").alias("weight")))


def cosupp(spark: SparkSession, sf_dir: str) -> PartitionedGraph:
    """Suppliers met in one order; owner is the nation."""
    met = met_pairs(_table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey"))
    supp = _table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("vid"), F.col("s_nationkey").cast("bigint").alias("sg"))
    return PartitionedGraph(supp, met.select("src", "dst", F.expr("1000000 div n").alias("weight")))


def order_cite(spark: SparkSession, sf_dir: str) -> PartitionedGraph:
    """Each order points at the two orders before it that hold the same part; owner is the year."""
    orders = _table(spark, sf_dir, "orders").select("o_orderkey", "o_orderdate")
    lines = _table(spark, sf_dir, "lineitem").select("l_partkey", F.col("l_orderkey").alias("o_orderkey")).distinct().join(orders, "o_orderkey")
    w = Window.partitionBy("l_partkey").orderBy("o_orderdate", "o_orderkey")
    before = lines.select("o_orderkey", "o_orderdate", *[F.lag(F.struct("o_orderkey", "o_orderdate"), k).over(w).alias(f"p{k}") for k in (1, 2)])
    arrows = before.select(F.col("o_orderkey").alias("src"), "o_orderdate", F.explode(F.array("p1", "p2")).alias("p")).where("p is not null")
    days = F.date_diff("o_orderdate", F.col("p.o_orderdate")).cast("bigint")
    edges = symmetrize(arrows.select("src", F.col("p.o_orderkey").alias("dst"), days.alias("weight")))
    return PartitionedGraph(orders.select(F.col("o_orderkey").alias("vid"), F.year("o_orderdate").cast("bigint").alias("sg")), edges)


def order_cite_range(spark: SparkSession, sf_dir: str, parts: int = 8) -> PartitionedGraph:
    """The same citations under a partition that ignores time: equal ranges of the order keys."""
    g = order_cite(spark, sf_dir)
    n = g.vertices.agg(F.max("vid") + 1).first()[0] or 1
    return g.with_partition(F.expr(f"vid * {parts} div {n}"))


def order_cite_arrows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(src, dst): each order and the two orders before it that hold the same part, newer to older, repeats kept."""
    orders = _table(spark, sf_dir, "orders").select("o_orderkey", "o_orderdate")
    lines = _table(spark, sf_dir, "lineitem").select("l_partkey", F.col("l_orderkey").alias("o_orderkey")).distinct().join(orders, "o_orderkey")
    w = Window.partitionBy("l_partkey").orderBy("o_orderdate", "o_orderkey")
    before = lines.select(F.col("o_orderkey").alias("src"), F.array(F.lag("o_orderkey", 1).over(w), F.lag("o_orderkey", 2).over(w)).alias("p"))
    return before.select("src", F.explode("p").alias("dst")).where("dst is not null")


#: Languages that page addresses name.
LANGUAGES = ("en", "fr", "de", "es")


def page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(page_id, href): the addresses that each page links to, repeats kept."""
    found = F.explode(F.regexp_extract_all("html", F.lit('<a href="([^"]+)"'), 1))
    return _table(spark, sf_dir, "pages").select("page_id", found.alias("href")).select("page_id", F.rtrim("href", F.lit(".,")).alias("href"))


def page_owners(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(vid, sg): pages and the language in their own address, 0 for none."""
    lang = F.array_position(F.array(*map(F.lit, LANGUAGES)), F.regexp_extract("url", "/([a-z]{2})/", 1))
    return _table(spark, sf_dir, "pages").select(F.col("page_id").alias("vid"), F.coalesce(lang, F.lit(0)).cast("bigint").alias("sg"))


def page_colink(spark: SparkSession, sf_dir: str) -> PartitionedGraph:
    """Pages that link to one address; weight falls with the addresses shared; owner is the language in the page's own address."""
    links = page_links(spark, sf_dir).distinct()
    pairs = links.alias("x").join(links.alias("y"), F.expr("x.href = y.href and x.page_id < y.page_id"))
    met = pairs.groupBy(F.col("x.page_id").alias("src"), F.col("y.page_id").alias("dst")).agg(F.count("*").alias("n"))
    return PartitionedGraph(page_owners(spark, sf_dir), met.select("src", "dst", F.expr("1000 div n").alias("weight")))


def user_coact(spark: SparkSession, sf_dir: str, minutes: int = 60) -> PartitionedGraph:
    """Users with an event of one type in one window; weight falls with the pairs of such events; owner is the id modulo 4."""
    events = _table(spark, sf_dir, "events")
    window = F.struct(F.date_trunc("hour", "ts").alias("h"), F.floor(F.minute("ts") / minutes).alias("m"))
    acts = events.select("user_id", "event_type", window.alias("w")).groupBy("user_id", "event_type", "w").agg(F.count("*").alias("n"))
    met = coact_pairs(acts)
    users = events.select(F.col("user_id").alias("vid")).distinct()
    return PartitionedGraph(users.select("vid", F.pmod("vid", F.lit(4)).cast("bigint").alias("sg")), met.select("src", "dst", F.expr("1000000 div n").alias("weight")))


#: Acts of a block of users that meets another one in a task, about, and pairs of users counted at once.
COACT_BLOCK, COACT_PAIRS = 300_000, 1 << 21


def coact_pairs(acts: DataFrame) -> DataFrame:
    """(src, dst, n): pairs of events of two users that share type and window, of acts (user_id, event_type, w, n).

    Users are hashed to blocks, packed acts of two blocks meet in a task, and their pairs are summed in a table of users by
    users, a strip at a time: pairs of acts are neither shuffled nor held.
    """
    import numpy as np
    import pyarrow as pa

    from ..operators.kernels import colour_of, packed_longs, unpacked_longs

    shared = spill(acts.select("event_type", "w").distinct().withColumn("g", F.monotonically_increasing_id()))
    acts = spill(acts.where("user_id is not null").join(shared, ["event_type", "w"]).select(F.col("user_id").cast("bigint"), "g", F.col("n").cast("bigint")))
    blocks = max(1, -(-acts.count() // COACT_BLOCK))

    def pack(batches):
        held, n = [], 0

        def flush() -> pa.RecordBatch:
            user, g, k = (np.concatenate([np.asarray(b.column(c)) for b in held]) for c in range(3))
            block = colour_of(user, blocks)
            order = np.lexsort((user, g, block))
            user, g, k, block = (x[order] for x in (user, g, k, block))
            found, at = np.unique(block, return_index=True)
            cuts = [*at.tolist(), len(block)]
            blobs = [packed_longs(user[a:b], np.diff(g[a:b], prepend=0), k[a:b]) for a, b in zip(cuts, cuts[1:], strict=False)]
            return pa.RecordBatch.from_arrays([pa.array(found.astype(np.int32)), pa.array(blobs, pa.binary())], ["p", "blob"])

        for batch in batches:
            held.append(batch)
            n += len(batch)
            if n >= 1_000_000:
                yield flush()
                held, n = [], 0
        if n:
            yield flush()

    def meet(batches):
        for batch in batches:
            for p, q, rows in zip(*(batch.column(c).to_pylist() for c in range(3)), strict=True):
                sides = []
                for side in (p, q):
                    got = [unpacked_longs(r["blob"], 3) for r in rows if r["p"] == side]
                    sides.append([np.concatenate(x) for x in zip(*((u, np.cumsum(g), k) for u, g, k in got), strict=True)] if got else None)
                if sides[0] is not None and sides[1] is not None:
                    yield from strips(*sides, p == q)

    def strips(left, right, same: bool):
        user, g, n = left
        rows, row = np.unique(user, return_inverse=True)
        cols, col = np.unique(right[0], return_inverse=True)
        order = np.argsort(right[1], kind="stable")
        col, g2, n2 = col[order], right[1][order], right[2][order]
        order = np.argsort(row, kind="stable")
        row, g, n = row[order], g[order], n[order]
        start = np.searchsorted(g2, g, "left")
        k = np.searchsorted(g2, g, "right") - start
        high = max(1, COACT_PAIRS // len(cols))
        for top in range(0, len(rows), high):
            many = min(high, len(rows) - top)
            a, b = np.searchsorted(row, (top, top + many))
            table = np.zeros(many * len(cols), np.int64)
            ends = np.cumsum(k[a:b])
            at = a
            while at < b:
                done = int(ends[at - a - 1]) if at > a else 0
                stop = max(at + 1, a + int(np.searchsorted(ends, done + COACT_PAIRS, "right")))
                part = k[at:stop]
                place = np.arange(int(part.sum())) + np.repeat(start[at:stop] - (np.cumsum(part) - part), part)
                where = np.repeat((row[at:stop] - top) * len(cols), part) + col[place]
                np.add.at(table, where, np.repeat(n[at:stop], part) * n2[place])
                at = stop
            hit = np.flatnonzero(table)
            x, y, total = rows[top + hit // len(cols)], cols[hit % len(cols)], table[hit]
            if same:
                once = x < y
                x, y, total = x[once], y[once], total[once]
            if len(x):
                yield pa.RecordBatch.from_arrays([pa.array(np.minimum(x, y)), pa.array(np.maximum(x, y)), pa.array(total)], ["src", "dst", "n"])

    packed = acts.mapInArrow(pack, "p int, blob binary")
    other = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("k")
    dealt = packed.select("p", "blob", other).select(F.least("p", "k").alias("i"), F.greatest("p", "k").alias("j"), F.struct("p", "blob").alias("r"))
    # a task for each few meetings, so that their blobs fit into a batch
    dealt = dealt.repartition(min(8192, blocks * (blocks + 1) // 2), "i", "j")
    return dealt.groupBy("i", "j").agg(F.collect_list("r").alias("rows")).mapInArrow(meet, "src bigint, dst bigint, n bigint")


#: Rows of a bucket of groups whose pairs are formed in a task, about; least number of buckets; buckets of pairs for each of
#: these; pairs that a task sums at once.
MET_ROWS, MET_BUCKETS, MET_SPREAD, MET_PAIRS = 1_000_000, 8, 2, 1 << 21


def met_pairs(rows: DataFrame) -> DataFrame:
    """(src, dst, n): members that share a group, src < dst, and the pairs of their rows that do, of rows (group, member).

    Rows travel packed to the bucket of their group, pairs are formed and summed there and travel packed to the bucket of
    their smaller member: neither is a row of a shuffle. Rows with a null play no part.
    """
    import numpy as np
    import pyarrow as pa

    from ..operators.kernels import colour_of, packed_edges, packed_longs, pairs_within, summed, unpacked_edges, unpacked_longs

    buckets = max(MET_BUCKETS, -(-rows.count() // MET_ROWS))
    spread = buckets * MET_SPREAD

    def pack(batches):
        held, n = [], 0

        def flush() -> pa.RecordBatch:
            group, member = (np.concatenate([np.asarray(b.column(c)) for b in held]) for c in range(2))
            bucket = colour_of(group, buckets)
            order = np.lexsort((member, group, bucket))
            group, member, bucket = group[order], member[order], bucket[order]
            found, at = np.unique(bucket, return_index=True)
            cuts = [*at.tolist(), len(bucket)]
            blobs = [packed_longs(np.diff(group[a:b], prepend=0), member[a:b]) for a, b in zip(cuts, cuts[1:], strict=False)]
            return pa.RecordBatch.from_arrays([pa.array(found.astype(np.int32)), pa.array(blobs, pa.binary())], ["p", "blob"])

        for batch in batches:
            held.append(batch)
            n += len(batch)
            if n >= 2 * MET_ROWS:
                yield flush()
                held, n = [], 0
        if n:
            yield flush()

    def form(batches):
        got = [unpacked_longs(x.as_py(), 2) for batch in batches for x in batch.column("blob")]
        group, member = np.concatenate([np.cumsum(g) for g, _ in got]), np.concatenate([m for _, m in got])
        del got
        for src, dst, n in pairs_within(group, member, MET_PAIRS):
            bucket = colour_of(src, spread)
            order = np.argsort(bucket, kind="stable")
            src, dst, n, bucket = src[order], dst[order], n[order], bucket[order]
            found, at = np.unique(bucket, return_index=True)
            cuts = [*at.tolist(), len(bucket)]
            blobs = [(packed_edges(src[a:b], dst[a:b]), packed_longs(n[a:b])) for a, b in zip(cuts, cuts[1:], strict=False)]
            edges, ns = zip(*blobs, strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(found.astype(np.int32)), pa.array(edges, pa.binary()), pa.array(ns, pa.binary())], ["p", "blob", "ns"])

    def merge(parts: list[tuple]) -> tuple:
        src, dst, n = (np.concatenate(x) for x in zip(*parts, strict=True))
        ids, code = np.unique(np.concatenate([src, dst]), return_inverse=True)
        key, n = summed(code[: len(src)].astype(np.int64) * len(ids) + code[len(src) :], n)
        return ids[key // len(ids)], ids[key % len(ids)], n

    def add(batches):
        parts, fresh = [], 0
        for batch in batches:
            for blob, ns in zip(batch.column("blob"), batch.column("ns"), strict=True):
                ids, s, d = unpacked_edges(blob.as_py())
                parts.append((ids[s], ids[d], *unpacked_longs(ns.as_py(), 1)))
                fresh += len(s)
                if fresh > MET_PAIRS:
                    parts, fresh = [merge(parts)], 0
        table = pa.table(dict(zip(("src", "dst", "n"), merge(parts), strict=True)))
        yield from table.to_batches(max_chunksize=1 << 17)

    # Spark streams the batches of a group to functions so marked
    for function in (form, add):
        function.__annotations__ = {"batches": Iterator[pa.RecordBatch], "return": Iterator[pa.RecordBatch]}
    group, member = (F.col(c) for c in rows.columns)
    longs = rows.where(group.isNotNull() & member.isNotNull()).select(group.cast("bigint"), member.cast("bigint"))
    # by number: packed rows are few bytes for much work, so that Spark would deal them to too few tasks
    formed = longs.mapInArrow(pack, "p int, blob binary").repartition(buckets, "p").groupBy("p").applyInArrow(form, "p int, blob binary, ns binary")
    return formed.repartition(spread, "p").groupBy("p").applyInArrow(add, "src bigint, dst bigint, n bigint")


#: Added to part keys where customers and parts share one id space.
PART_BASE = 1_000_000_000


def cust_part(spark: SparkSession, sf_dir: str) -> PartitionedGraph:
    """Customers and the parts they ordered (two-sided, so no triangles); owners are nations and, from 100 on, brands."""
    orders = _table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), F.col("o_custkey").alias("src"))
    lines = _table(spark, sf_dir, "lineitem").select("l_orderkey", (F.col("l_partkey") + PART_BASE).alias("dst"))
    met = lines.join(orders, "l_orderkey").groupBy("src", "dst").agg(F.count("*").alias("n"))
    cust = _table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("vid"), F.col("c_nationkey").cast("bigint").alias("sg"))
    part = _brand(_table(spark, sf_dir, "part")).select((F.col("vid") + PART_BASE).alias("vid"), (F.col("sg") + 100).alias("sg"))
    return PartitionedGraph(cust.unionByName(part), met.select("src", "dst", F.expr("1000000 div n").alias("weight")))


def conv_next(spark: SparkSession, sf_dir: str) -> PartitionedGraph:
    """Turns of a conversation in order: paths that never leave their owner, the conversation."""
    turns = _table(spark, sf_dir, "conversations").select("conv_id", (F.col("conv_id") * 10000 + F.col("turn")).alias("vid")).distinct()
    edges = turns.select(F.col("vid").alias("src"), (F.col("vid") + 1).alias("dst")).join(turns.select(F.col("vid").alias("dst")), "dst", "left_semi")
    return PartitionedGraph(turns.select("vid", F.col("conv_id").cast("bigint").alias("sg")), edges.select("src", "dst", F.lit(1).cast("bigint").alias("weight")))


def emb_knn(spark: SparkSession, sf_dir: str, k: int = 8, dims: int = 64) -> PartitionedGraph:
    """Each vector and its ``k`` nearest by straight distance (every vector is a stated query against all, in blocks of
    rows, compared in numpy; all of one length, without nulls); weight is the distance in millionths; owner is the label."""
    import numpy as np
    import pyarrow as pa

    rows = _table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("vid"), F.col("embedding").cast("array<double>").alias("x"), F.col("label").cast("bigint").alias("sg"))
    rows = spill(rows)
    blocks = max(1, -(-rows.count() // KNN_BLOCK))
    block = F.pmod(F.xxhash64("vid"), F.lit(blocks)).cast("int")
    asked, far = (rows.select("vid", "x", block.alias("p")) for _ in range(2))
    other = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    asked, far = asked.select("vid", "x", "p", other.alias("q")), far.select("vid", "x", F.col("p").alias("q"), other.alias("p"))

    def matrix(table: pa.Table) -> tuple[np.ndarray, np.ndarray]:
        table = table.sort_by("vid")
        return table.column("vid").to_numpy(), np.array(table.column("x").to_pylist(), np.float64).reshape(len(table), -1)

    def nearest(left: pa.Table, right: pa.Table) -> pa.Table:
        out: list[tuple] = []
        if len(left) and len(right):
            (src, x), (dst, y) = matrix(left), matrix(right)
            for at, row in zip(src, x, strict=True):
                # one component after the other, as the sum is defined: equal sums stay equal
                d = np.zeros(len(dst))
                for c in range(y.shape[1]):
                    d += (y[:, c] - row[c]) ** 2
                d = np.sqrt(d)
                d[dst == at] = np.inf
                best = np.lexsort((dst, d))[: k + 1] if len(d) <= k else _least(d, dst, k)
                out.extend((int(at), int(dst[j]), float(d[j])) for j in best[:k] if dst[j] != at)
        cols = list(zip(*out, strict=True)) or [[]] * 3
        return pa.table({"src": pa.array(cols[0], pa.int64()), "dst": pa.array(cols[1], pa.int64()), "d": pa.array(cols[2], pa.float64())})

    every = asked.groupBy("p", "q").cogroup(far.groupBy("p", "q")).applyInArrow(nearest, "src bigint, dst bigint, d double")
    w = Window.partitionBy("src").orderBy("d", "dst")
    best = every.withColumn("r", F.row_number().over(w)).where(F.col("r") <= k)
    # written once: callers read the edges several times
    return PartitionedGraph(rows.select("vid", "sg"), spill(symmetrize(best.select("src", "dst", F.round(F.col("d") * 1e6).cast("bigint").alias("weight")))))


#: Vectors of a block that is compared with another one in a task, about.
KNN_BLOCK = 2000


def _least(d, ids, k: int):
    """Places of the ``k`` least distances, ties to the lesser id."""
    import numpy as np

    near = np.flatnonzero(d <= np.partition(d, k - 1)[k - 1])
    return near[np.lexsort((ids[near], d[near]))][:k]


GRAPHS = {
    "nation": nation_trade, "cosupp": cosupp, "copart": copart, "copart_strong": copart_strong, "order_cite": order_cite,
    "order_range": order_cite_range, "page_colink": page_colink, "user_coact": user_coact, "cust_part": cust_part,
    "conv_next": conv_next, "emb_knn": emb_knn,
}
