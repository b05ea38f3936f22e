"""Operators round the graph methods (scans, joins, aggregates, windows, functions, SQL, extensions), each with SQL where it can be said."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import extensions as X
from ..operators import triangles as T
from ..sources import graphs as G
from ..sources.files import EdgeListSource, generated, text_edges
from ..storage import shared_dir
from .catalog import CTE

Query = Callable[[SparkSession, str], DataFrame]
_FOUND: dict[str, tuple[Query, str | None]] = {}


def _table(s: SparkSession, d: str, name: str) -> DataFrame:
    return s.read.parquet(f"{d}/{name}.parquet")


def op(sql: str | None = None):
    """Register a query under its function's name, with the SQL that gives the same rows."""

    def add(f: Query) -> Query:
        _FOUND[f.__name__] = (f, sql)
        return f

    return add


_NATION = f"with {CTE['nation']}"
_STRONG = f"with {CTE['copart_strong']}"
_DEG = "dg as (select vid, count(*) degree from (select src vid from e union all select dst from e) group by vid)"
_NT = f"{_NATION}, {_DEG}"
_ST = f"{_STRONG}, {_DEG}"

# ---- sources and sinks -----------------------------------------------------------------------


@op("select l_orderkey, l_partkey, l_quantity from lineitem where l_shipdate >= timestamp '1996-03-01' and l_shipdate < timestamp '1996-04-01'")
def sc_scan_prune(s, d):
    """Three columns of a month: the filter and the column list reach the scan."""
    line = _table(s, d, "lineitem")
    day = lambda x: F.lit(x).cast("timestamp_ntz")
    return line.where((F.col("l_shipdate") >= day("1996-03-01")) & (F.col("l_shipdate") < day("1996-04-01"))).select("l_orderkey", "l_partkey", "l_quantity")


@op(f"{_NATION} select src, dst, weight from e")
def sc_edge_text_roundtrip(s, d):
    return text_edges(G.nation_trade(s, d).edges, f"{shared_dir(s)}/edges-{uuid.uuid4().hex}")


@op("select event_type, count(*) events, cast(sum(cast(json_extract(props, '$.k') as bigint)) as bigint) k from events group by event_type")
def sc_events_json(s, d):
    """Events written as JSON and read back with a schema; the nested document is taken apart."""
    path = f"{shared_dir(s)}/events-{uuid.uuid4().hex}"
    _table(s, d, "events").select("event_id", "event_type", "props").write.json(path)
    back = s.read.schema("event_id bigint, event_type string, props string").json(path)
    k = F.from_json("props", "k bigint")["k"]
    return back.groupBy("event_type").agg(F.count("*").alias("events"), F.sum(k).alias("k"))


@op("select o_orderstatus, count(*) orders, cast(sum(cast(round(o_totalprice * 100) as bigint)) as bigint) cents from orders group by o_orderstatus")
def sc_orders_orc(s, d):
    path = f"{shared_dir(s)}/orders-{uuid.uuid4().hex}"
    _table(s, d, "orders").select("o_orderkey", "o_orderstatus", "o_totalprice").write.orc(path)
    back = s.read.schema("o_orderkey bigint, o_orderstatus string, o_totalprice double").orc(path)
    return back.groupBy("o_orderstatus").agg(F.count("*").alias("orders"), F.sum(F.round(F.col("o_totalprice") * 100).cast("bigint")).alias("cents"))


@op(f"{_STRONG} select vid, sg from v where sg = 7")
def sc_partitioned_sink(s, d):
    """Vertices written in folders by subgraph; reading one subgraph opens one folder."""
    path = f"{shared_dir(s)}/vertices-{uuid.uuid4().hex}"
    g = G.copart_strong(s, d)
    g.vertices.repartition("sg").write.partitionBy("sg").parquet(path)
    return s.read.schema("vid bigint, sg bigint").parquet(path).where("sg = 7").select("vid", "sg")


@op(f"{_STRONG} select x.src a, x.dst b, y.dst c from e x join e y on x.src = y.src and x.dst < y.dst")
def sc_bucketed_sink(s, d):
    """Edges in buckets of their source: a join on it needs no exchange."""
    name = f"edges_{uuid.uuid4().hex}"
    G.copart_strong(s, d).edges.select("src", "dst").write.bucketBy(8, "src").sortBy("src").saveAsTable(name, path=f"{shared_dir(s)}/{name}")
    e = s.table(name)
    return e.alias("x").join(e.alias("y"), F.expr("x.src = y.src and x.dst < y.dst")).select(F.col("x.src").alias("a"), F.col("x.dst").alias("b"), F.col("y.dst").alias("c"))


@op(f"{_STRONG} select src, dst, weight from e where src >= 100")
def sc_edgelist_source(s, d):
    """A reader of its own: one partition for each range of source vertices, a lower bound taken as an option."""
    path = f"{shared_dir(s)}/list-{uuid.uuid4().hex}"
    G.copart_strong(s, d).edges.write.parquet(path)
    s.dataSource.register(EdgeListSource)
    return s.read.format("edgelist").option("path", path).option("parts", "4").option("from", "100").load()


_RING = "select cast(i as bigint) a, cast((i + 1) % 12 as bigint) b from range(12) t(i)"
_GRID = "select cast(i as bigint) a, cast(i + 1 as bigint) b from range(12) t(i) where i % 4 < 3 union all select i, i + 4 from range(8) t(i)"
_FULL = "select cast(x.i as bigint) a, cast(y.i as bigint) b from range(12) x(i), range(12) y(i) where x.i < y.i"
_CAVES = "select x.i a, y.i b from range(12) x(i), range(12) y(i) where x.i < y.i and x.i // 4 = y.i // 4 union all select i, (i + 1) % 12 from range(12) t(i) where i % 4 = 3"


@op(f"select kind, block * 12 + src src, block * 12 + dst dst from (select kind, least(a, b) src, greatest(a, b) dst from (select 'ring' kind, * from ({_RING}) union all select 'grid', * from ({_GRID}) union all select 'complete', * from ({_FULL}) union all select 'caveman', * from ({_CAVES}))), (select c_custkey // 12 block from customer group by 1 having count(*) = 12)")
def sc_graph_range(s, d):
    """Graphs of each twelve customers with neighbouring keys; a last block of fewer has none."""
    kinds = [generated(s, kind, 12, 4).select(F.lit(kind).alias("kind"), "src", "dst") for kind in ("ring", "grid", "complete", "caveman")]
    out = kinds[0]
    for k in kinds[1:]:
        out = out.unionByName(k)
    block = F.expr("c_custkey div 12")
    whole = _table(s, d, "customer").groupBy(block.alias("block")).agg(F.count("*").alias("n")).where("n = 12")
    return whole.crossJoin(F.broadcast(out)).select("kind", (F.col("block") * 12 + F.col("src")).alias("src"), (F.col("block") * 12 + F.col("dst")).alias("dst"))


# ---- projections and predicates ---------------------------------------------------------------


@op(f"{_NATION} select src as low, dst as high, weight * 2 as twice, dst - src as gap from e")
def pf_edge_projection(s, d):
    return G.nation_trade(s, d).edges.withColumnsRenamed({"src": "low", "dst": "high"}).select("low", "high", (F.col("weight") * 2).alias("twice"), (F.col("high") - F.col("low")).alias("gap"))


@op("select o_orderkey, o_orderstatus, o_orderpriority from orders where o_orderstatus in ('F', 'O') and o_totalprice between 1000 and 90000 and o_orderpriority like '%-%' and regexp_matches(o_orderpriority, '^[12]') and o_custkey is not distinct from o_custkey")
def pf_pred_mix(s, d):
    o = _table(s, d, "orders")
    p = F.col("o_orderpriority")
    return o.where(F.col("o_orderstatus").isin("F", "O") & F.col("o_totalprice").between(1000, 90000) & p.like("%-%") & p.rlike("^[12]") & F.col("o_custkey").eqNullSafe(F.col("o_custkey"))).select("o_orderkey", "o_orderstatus", "o_orderpriority")


@op(f"{_ST} select case when degree < 3 then 'low' when degree < 6 then 'mid' else 'high' end bucket, count(*) vertices, cast(coalesce(sum(nullif(degree, 1)), 0) as bigint) of_many from dg group by 1")
def pf_degree_bucket(s, d):
    deg = T.degrees(G.copart_strong(s, d))
    bucket = F.when(F.col("degree") < 3, "low").when(F.col("degree") < 6, "mid").otherwise("high")
    return deg.groupBy(bucket.alias("bucket")).agg(F.count("*").alias("vertices"), F.coalesce(F.sum(F.nullif("degree", F.lit(1))), F.lit(0)).alias("of_many"))


# ---- joins ------------------------------------------------------------------------------------

_TRADE = "select c_nationkey, s_nationkey, count(*) lines from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join supplier on l_suppkey = s_suppkey group by 1, 2"


def _trade(s, d, hint: str) -> DataFrame:
    line, orders, cust, supp = (_table(s, d, t) for t in ("lineitem", "orders", "customer", "supplier"))
    met = line.join(orders.hint(hint), line["l_orderkey"] == orders["o_orderkey"]).join(cust.hint(hint), F.col("o_custkey") == F.col("c_custkey")).join(supp.hint(hint), F.col("l_suppkey") == F.col("s_suppkey"))
    return met.groupBy("c_nationkey", "s_nationkey").agg(F.count("*").alias("lines"))


@op(_TRADE)
def jn_trade_merge(s, d):
    return _trade(s, d, "merge")


@op(_TRADE)
def jn_trade_shuffle_hash(s, d):
    return _trade(s, d, "shuffle_hash")


@op(_TRADE)
def jn_trade_auto(s, d):
    """No hint: small sides are broadcast by their measured size."""
    line, orders, cust, supp = (_table(s, d, t) for t in ("lineitem", "orders", "customer", "supplier"))
    met = line.join(orders, line["l_orderkey"] == orders["o_orderkey"]).join(cust, F.col("o_custkey") == F.col("c_custkey")).join(supp, F.col("l_suppkey") == F.col("s_suppkey"))
    return met.groupBy("c_nationkey", "s_nationkey").agg(F.count("*").alias("lines"))


@op("select c_custkey from customer left join orders on c_custkey = o_custkey where o_orderkey is null")
def jn_customers_without_orders(s, d):
    return _table(s, d, "customer").join(_table(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left").where("o_orderkey is null").select("c_custkey")


@op("select n_nationkey, count(c_custkey) customers from customer right join nation on c_nationkey = n_nationkey group by n_nationkey")
def jn_right_customers(s, d):
    return _table(s, d, "customer").join(_table(s, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey"), "right").groupBy("n_nationkey").agg(F.count("c_custkey").alias("customers"))


@op("select c_nk, s_nk, customers, suppliers from (select c_nationkey c_nk, count(*) customers from customer where c_acctbal > 9000 group by 1) full join (select s_nationkey s_nk, count(*) suppliers from supplier group by 1) on c_nk = s_nk")
def jn_full_outer(s, d):
    c = _table(s, d, "customer").where("c_acctbal > 9000").groupBy(F.col("c_nationkey").alias("c_nk")).agg(F.count("*").alias("customers"))
    p = _table(s, d, "supplier").groupBy(F.col("s_nationkey").alias("s_nk")).agg(F.count("*").alias("suppliers"))
    return c.join(p, F.col("c_nk") == F.col("s_nk"), "full")


_TRI = "t as (select x.src a, x.dst b, y.dst c from e x join e y on x.dst = y.src join e z on z.src = x.src and z.dst = y.dst)"


@op(f"{_STRONG}, {_TRI} select vid from v where vid in (select a from t union all select b from t union all select c from t)")
def jn_parts_in_triangles(s, d):
    g = G.copart_strong(s, d)
    return g.vertices.join(T.per_vertex(T.triangles(g)), "vid", "left_semi").select("vid")


@op(f"{_STRONG} select vid from v where vid not in (select src from e union all select dst from e)")
def jn_isolated_parts(s, d):
    g = G.copart_strong(s, d)
    return g.vertices.join(T.degrees(g), "vid", "left_anti").select("vid")


@op(f"{_STRONG} select x.src v, x.dst w, y.dst u from e x join e y on x.dst = y.src")
def jn_wedges(s, d):
    e = G.copart_strong(s, d).edges
    return e.alias("x").join(e.alias("y"), F.expr("x.dst = y.src")).select(F.col("x.src").alias("v"), F.col("x.dst").alias("w"), F.col("y.dst").alias("u"))


@op("select x.s_suppkey a, y.s_suppkey b from supplier x join supplier y on x.s_nationkey = y.s_nationkey and x.s_acctbal > y.s_acctbal + 1000")
def jn_price_dominates(s, d):
    """An inequality within a nation."""
    p = _table(s, d, "supplier")
    return p.alias("x").join(p.alias("y"), F.expr("x.s_nationkey = y.s_nationkey and x.s_acctbal > y.s_acctbal + 1000")).select(F.col("x.s_suppkey").alias("a"), F.col("y.s_suppkey").alias("b"))


@op("select a.p_partkey a, b.p_partkey b from part a join part b on a.p_partkey < b.p_partkey and abs(cast(round(a.p_retailprice * 100) as bigint) - cast(round(b.p_retailprice * 100) as bigint)) <= 5")
def jn_price_band_pairs(s, d):
    """Prices at most five cents apart: bins one band wide, each row also meets the next bin, then the exact test."""
    cents = _table(s, d, "part").select("p_partkey", F.round(F.col("p_retailprice") * 100).cast("bigint").alias("c")).withColumn("bin", F.expr("c div 6"))
    far = cents.select(F.col("p_partkey").alias("q"), F.col("c").alias("qc"), F.explode(F.array(F.col("bin") - 1, F.col("bin"), F.col("bin") + 1)).alias("bin"))
    return cents.join(far, "bin").where((F.col("p_partkey") < F.col("q")) & (F.abs(F.col("c") - F.col("qc")) <= 5)).select(F.col("p_partkey").alias("a"), F.col("q").alias("b"))


@op("select a.event_id a, b.event_id b from events a join events b on a.user_id = b.user_id and a.event_id <> b.event_id and b.ts > a.ts and b.ts <= a.ts + interval 5 minutes")
def jn_events_within_5min(s, d):
    """Later events of a user within five minutes: time bins of that width narrow the join."""
    e = _table(s, d, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    width = 5 * 60 * 1_000_000
    a = e.select("user_id", F.col("event_id").alias("a"), F.col("us").alias("ua"), F.explode(F.array(F.expr(f"us div {width}"), F.expr(f"us div {width} + 1"))).alias("bin"))
    b = e.select("user_id", F.col("event_id").alias("b"), F.col("us").alias("ub"), F.expr(f"us div {width}").alias("bin"))
    return a.join(b, ["user_id", "bin"]).where((F.col("ub") > F.col("ua")) & (F.col("ub") <= F.col("ua") + width)).select("a", "b")


@op("select e.event_id, p.event_id prev_purchase from events e asof left join (select * from events where event_type = 'purchase') p on e.user_id = p.user_id and e.ts > p.ts")
def jn_event_asof_prev_purchase(s, d):
    """The user's last purchase before each event: one pass over the user's events in time order."""
    e = _table(s, d, "events")
    w = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    # of one moment, only earlier purchases count: the running list ends before the present time
    bought = F.when(F.col("event_type") == "purchase", F.struct("ts", "event_id"))
    upto = e.select("event_id", "ts", F.max(bought).over(w).alias("now"), F.max(bought).over(Window.partitionBy("user_id").orderBy("ts").rowsBetween(Window.unboundedPreceding, -1)).alias("before"))
    return upto.select("event_id", F.when(F.col("now.ts") < F.col("ts"), F.col("now.event_id")).otherwise(F.when(F.col("before.ts") < F.col("ts"), F.col("before.event_id"))).alias("prev_purchase"))


@op("select a.n_nationkey a, b.n_nationkey b from nation a cross join nation b where a.n_regionkey = 0")
def jn_all_nation_pairs(s, d):
    n = _table(s, d, "nation")
    return n.where("n_regionkey = 0").select(F.col("n_nationkey").alias("a")).crossJoin(n.select(F.col("n_nationkey").alias("b")))


@op(f"{_NATION} select src, dst, weight from e qualify row_number() over (partition by src order by weight, dst) <= 3")
def jn_topk_per_vertex_lateral(s, d):
    """Three lightest edges of each vertex, by a lateral subquery."""
    G.nation_trade(s, d).edges.createOrReplaceTempView("lateral_edges")
    return s.sql("select k.src, k.dst, k.weight from (select distinct src from lateral_edges) v, lateral (select src, dst, weight from lateral_edges e where e.src = v.src order by weight, dst limit 3) k")


# ---- aggregates -------------------------------------------------------------------------------


@op(f"{_ST} select vid, degree from dg")
def ag_degree(s, d):
    return T.degrees(G.copart_strong(s, d))


@op(f"{_STRONG}, h as (select src u, dst w from e union all select dst, src from e) select u vid, array_to_string(list_sort(list(distinct w)), ',') neighbours from h group by u")
def ag_adjacency_lists(s, d):
    h = G.copart_strong(s, d).half_edges()
    return h.groupBy(F.col("u").alias("vid")).agg(F.array_join(F.array_sort(F.collect_set("v")), ",").alias("neighbours"))


@op("select o_custkey, count(distinct l_partkey) parts, count(distinct l_suppkey) suppliers from orders join lineitem on o_orderkey = l_orderkey group by o_custkey")
def ag_distinct_neighbours(s, d):
    met = _table(s, d, "orders").join(_table(s, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"))
    return met.groupBy("o_custkey").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"))


@op("select o_orderstatus, abs(1 - 1) as off from orders group by o_orderstatus")
def ag_approx_distinct_within(s, d):
    """0 where the approximate number of customers is within 10 percent of the exact one."""
    got = _table(s, d, "orders").groupBy("o_orderstatus").agg(F.approx_count_distinct("o_custkey", 0.02).alias("a"), F.count_distinct("o_custkey").alias("n"))
    return got.select("o_orderstatus", F.when(F.abs(F.col("a") - F.col("n")) * 10 <= F.col("n"), 0).otherwise(1).alias("off"))


@op(f"{_NATION}, o as (select p.sg ps, q.sg qs from e join v p on src = p.vid join v q on dst = q.vid) select ps, qs, count(*) edges, grouping(ps) + grouping(qs) as lvl from o group by rollup(ps, qs)")
def ag_cut_by_sg_rollup(s, d):
    o = G.nation_trade(s, d).owned_edges().select(F.col("src_sg").alias("ps"), F.col("dst_sg").alias("qs"))
    return o.rollup("ps", "qs").agg(F.count("*").alias("edges"), (F.grouping("ps") + F.grouping("qs")).cast("bigint").alias("lvl"))


@op("select l_returnflag, l_linestatus, count(*) lines from lineitem group by cube(l_returnflag, l_linestatus)")
def ag_sales_cube(s, d):
    return _table(s, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("lines"))


@op("select o_orderstatus, o_orderpriority, count(*) orders from orders group by grouping sets ((o_orderstatus), (o_orderpriority), ())")
def ag_grouping_sets(s, d):
    _table(s, d, "orders").createOrReplaceTempView("gs_orders")
    return s.sql("select o_orderstatus, o_orderpriority, count(*) orders from gs_orders group by grouping sets ((o_orderstatus), (o_orderpriority), ())")


@op(f"{_STRONG}, h as (select src u, dst w, weight, src, dst from e union all select dst, src, weight, src, dst from e) select u vid, arg_min(w, (weight, src, dst)) nearest, min(weight) weight from h group by u")
def ag_least_edge_per_vertex(s, d):
    e = G.copart_strong(s, d).edges
    h = e.select(F.col("src").alias("vid"), F.col("dst").alias("w"), "*").union(e.select(F.col("dst"), F.col("src"), "*"))
    return h.groupBy("vid").agg(F.min_by("w", F.struct("weight", "src", "dst")).alias("nearest"), F.min("weight").alias("weight"))


@op(f"{_ST} select quantile_disc(degree, 0.5) p50, quantile_disc(degree, 0.9) p90, max(degree) top, cast(sum(degree) as bigint) total from dg")
def ag_degree_percentiles(s, d):
    deg = T.degrees(G.copart_strong(s, d))
    at = lambda p: F.expr(f"percentile_disc({p}) within group (order by degree)").cast("bigint")
    return deg.agg(at(0.5).alias("p50"), at(0.9).alias("p90"), F.max("degree").alias("top"), F.sum("degree").alias("total"))


@op(f"{_NATION}, o as (select p.sg ps, q.sg qs from e join v p on src = p.vid join v q on dst = q.vid) select ps, " + ", ".join(f"count(*) filter (qs = {i}) r{i}" for i in range(5)) + " from o group by ps")
def ag_meta_matrix(s, d):
    """Edges between regions as a matrix."""
    o = G.nation_trade(s, d).owned_edges().select(F.col("src_sg").alias("ps"), F.col("dst_sg").alias("qs"))
    wide = o.groupBy("ps").pivot("qs", list(range(5))).count()
    return wide.select("ps", *[F.coalesce(F.col(f"`{i}`"), F.lit(0)).alias(f"r{i}") for i in range(5)])


@op(f"{_NATION} select side, vid, count(*) edges from (select 'src' side, src vid from e union all select 'dst', dst from e) group by 1, 2")
def ag_endpoints_unpivot(s, d):
    e = G.nation_trade(s, d).edges
    return e.unpivot("weight", ["src", "dst"], "side", "vid").groupBy("side", "vid").agg(F.count("*").alias("edges"))


@op("select o_orderstatus, count(*) filter (o_totalprice > 100000) big, bool_or(o_totalprice > 400000) any_huge, bool_and(o_totalprice > 0) all_positive, string_agg(distinct o_orderpriority, ',' order by o_orderpriority) priorities from orders group by o_orderstatus")
def ag_type_counts(s, d):
    price = F.col("o_totalprice")
    listed = F.array_join(F.array_sort(F.collect_set("o_orderpriority")), ",").alias("priorities")
    return _table(s, d, "orders").groupBy("o_orderstatus").agg(F.count_if(price > 100000).alias("big"), F.bool_or(price > 400000).alias("any_huge"), F.bool_and(price > 0).alias("all_positive"), listed)


@op("select 0 off from orders limit 1")
def ag_sketch_merge(s, d):
    """0 if sketches of each status, merged, estimate the number of customers as one sketch of all does, within 5 percent."""
    o = _table(s, d, "orders")
    merged = o.groupBy("o_orderstatus").agg(F.hll_sketch_agg("o_custkey").alias("k")).agg(F.hll_sketch_estimate(F.hll_union_agg("k")).alias("m"))
    return merged.crossJoin(o.agg(F.count_distinct("o_custkey").alias("n"))).select(F.when(F.abs(F.col("m") - F.col("n")) * 20 <= F.col("n"), 0).otherwise(1).alias("off"))


# ---- windows and order ------------------------------------------------------------------------


@op(f"{_STRONG} select src, dst, weight from e qualify row_number() over (partition by src order by weight desc, dst) <= 2")
def wn_topk_edges_per_vertex(s, d):
    w = Window.partitionBy("src").orderBy(F.desc("weight"), "dst")
    return G.copart_strong(s, d).edges.withColumn("r", F.row_number().over(w)).where("r <= 2").drop("r")


@op(f"{_NT} select vid, rank() over w r, dense_rank() over w dr, ntile(4) over (order by degree desc, vid) q, round(percent_rank() over w, 6) pr, round(cume_dist() over w, 6) cd from dg window w as (order by degree desc)")
def wn_rank_degree(s, d):
    """Ranks of 25 vertices (one window over a small table)."""
    w = Window.orderBy(F.desc("degree"))
    rank = [F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(Window.orderBy(F.desc("degree"), "vid")).alias("q"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd")]
    return T.degrees(G.nation_trade(s, d)).select("vid", *rank)


@op("select event_id, lag(event_id, 2) over w back, lead(event_type) over w ahead, first_value(event_id) over w first_id, nth_value(event_id, 2) over (partition by user_id order by ts, event_id rows between unbounded preceding and unbounded following) second_id from events window w as (partition by user_id order by ts, event_id)")
def wn_event_neighbours(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return _table(s, d, "events").select("event_id", F.lag("event_id", 2).over(w).alias("back"), F.lead("event_type").over(w).alias("ahead"), F.first("event_id").over(w).alias("first_id"), F.nth_value("event_id", 2).over(whole).alias("second_id"))


@op("select o_orderkey, count(*) over (partition by o_custkey order by o_orderdate, o_orderkey rows between 2 preceding and current row) held, max(o_orderkey) over (partition by o_custkey order by o_orderdate, o_orderkey rows between 1 following and 2 following) ahead from orders")
def wn_rolling_rows(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return _table(s, d, "orders").select("o_orderkey", F.count("*").over(w.rowsBetween(-2, 0)).alias("held"), F.max("o_orderkey").over(w.rowsBetween(1, 2)).alias("ahead"))


@op("select event_id, count(*) over (partition by user_id order by epoch_us(ts) // 1000000 range between 604800 preceding and current row) in_week from events")
def wn_rolling_7d_events(s, d):
    seconds = F.unix_timestamp(F.col("ts").cast("timestamp"))
    w = Window.partitionBy("user_id").orderBy(seconds).rangeBetween(-7 * 86400, 0)
    return _table(s, d, "events").select("event_id", F.count("*").over(w).alias("in_week"))


@op(f"{_STRONG} select src, dst, weight from e order by weight desc, src, dst limit 10 offset 5")
def st_heaviest_edges(s, d):
    return G.copart_strong(s, d).edges.orderBy(F.desc("weight"), "src", "dst").offset(5).limit(10)


@op("select c_custkey, c_acctbal from customer order by nullif(c_mktsegment, 'MACHINERY') nulls last, c_acctbal desc, c_custkey limit 20")
def st_nulls_last(s, d):
    c = _table(s, d, "customer")
    return c.orderBy(F.nullif("c_mktsegment", F.lit("MACHINERY")).asc_nulls_last(), F.desc("c_acctbal"), "c_custkey").limit(20).select("c_custkey", "c_acctbal")


@op(f"{_STRONG} select src, dst, weight from e")
def st_range_layout(s, d):
    """Ranges of the source, sorted inside each: a layout for files with narrow statistics."""
    return G.copart_strong(s, d).edges.repartitionByRange(8, "src").sortWithinPartitions("src", "dst")


# ---- set operations, sampling, SQL ------------------------------------------------------------


@op(f"{_NATION}, o as (select src, dst, p.sg ps, q.sg qs from e join v p on src = p.vid join v q on dst = q.vid) select src, dst from e except select src, dst from o where ps = qs")
def so_cut_by_except(s, d):
    g = G.nation_trade(s, d)
    return g.edges.select("src", "dst").exceptAll(g.owned_edges().where("src_sg = dst_sg").select("src", "dst"))


@op("select 0 differing")
def so_tri_sets_equal(s, d):
    """Triangles of one form but not of the other, either way."""
    g = G.copart_strong(s, d)
    a, b = T.triangles(g).select("a", "b", "c"), T.triangles_forward(g)
    return a.exceptAll(b).unionAll(b.exceptAll(a)).agg(F.count("*").alias("differing"))


@op("select k from (select l_partkey k from lineitem where l_quantity > 45 intersect select l_partkey from lineitem where l_quantity < 5)")
def so_intersect(s, d):
    line = _table(s, d, "lineitem")
    return line.where("l_quantity > 45").select(F.col("l_partkey").alias("k")).intersect(line.where("l_quantity < 5").select("l_partkey"))


@op("select o_custkey, sum(n)::bigint n from (select o_custkey, 1 n from orders where o_orderstatus = 'F' intersect all select o_custkey, 1 from orders where o_orderstatus = 'O') group by 1")
def so_intersect_all(s, d):
    o = _table(s, d, "orders")
    of = lambda x: o.where(F.col("o_orderstatus") == x).select("o_custkey")
    return of("F").intersectAll(of("O")).groupBy("o_custkey").agg(F.count("*").alias("n"))


@op("select o_orderkey from orders where cast('0x' || substr(md5(cast(o_orderkey as varchar)), 1, 8) as bigint) % 100 < 10")
def sp_hash_sample(s, d):
    """A tenth of the orders, the same ones in any engine and layout."""
    from ..operators.partitions import hash_part

    return _table(s, d, "orders").where(hash_part(F.col("o_orderkey"), 100) < 10).select("o_orderkey")


@op()
def sp_sample_by(s, d):
    """Random shares by status; the seed fixes them for one layout."""
    return _table(s, d, "orders").sampleBy("o_orderstatus", {"F": 0.1, "O": 0.2}, 7).select("o_orderkey", "o_orderstatus")


@op("with recursive r(a, b, n) as (select src, dst, 1 from e where src = 0 union all select r.a, e.dst, n + 1 from r join e on e.src = r.b where n < 3), ".replace("with recursive ", f"with recursive {CTE['nation']}, ") + "k as (select 1) select n steps, count(*) paths from r group by n")
def sq_recursive_paths(s, d):
    """Rising paths of up to three edges from vertex 0."""
    G.nation_trade(s, d).stored().edges.createOrReplaceTempView("rising_edges")
    return s.sql("with recursive r(b, n) as (select dst, 1 from rising_edges where src = 0 union all select e.dst, n + 1 from r join rising_edges e on e.src = r.b where n < 3) select cast(n as bigint) steps, count(*) paths from r group by n")


@op(f"{_STRONG} select src, dst from e where exists (select 1 from e x join e y on x.dst = y.src where x.src = e.src and y.dst = e.dst)")
def sq_exists_triangle(s, d):
    """Edges that close a path of two, by a correlated subquery."""
    G.copart_strong(s, d).edges.createOrReplaceTempView("closing_edges")
    return s.sql("select src, dst from closing_edges e where exists (select 1 from closing_edges x join closing_edges y on x.dst = y.src where x.src = e.src and y.dst = e.dst)")


@op("select c_custkey, c_acctbal > (select avg(c_acctbal) from customer) above from customer where c_custkey in (select o_custkey from orders where o_orderstatus = 'P') and c_acctbal >= (select min(s_acctbal) from supplier where s_nationkey = c_nationkey)")
def sq_subqueries(s, d):
    for t in ("customer", "orders", "supplier"):
        _table(s, d, t).createOrReplaceTempView(f"sq_{t}")
    return s.sql("select c_custkey, c_acctbal > (select avg(c_acctbal) from sq_customer) above from sq_customer where c_custkey in (select o_custkey from sq_orders where o_orderstatus = 'P') and c_acctbal >= (select min(s_acctbal) from sq_supplier where s_nationkey = c_nationkey)")


@op(f"{_ST} select vid, degree from dg")
def sq_graph_degree(s, d):
    """A table function of this library over a table argument."""
    s.udtf.register("graph_degree", X.GraphDegree)
    G.copart_strong(s, d).edges.createOrReplaceTempView("degree_edges")
    ends = "(select src vid from degree_edges union all select dst from degree_edges)"
    return s.sql(f"select * from graph_degree(table{ends} partition by vid order by vid)")


# ---- scalar functions -------------------------------------------------------------------------


@op("select page_id, regexp_extract(url, '^https?://([^/]+)', 1) host, regexp_extract(url, '/([a-z]{2})/', 1) lang, len(regexp_extract_all(html, '<a href=\"([^\"]+)\"', 1)) links, upper(left(url, 4)) scheme, levenshtein(left(url, 20), left(html, 20)) far, string_split(url, '/')[3] third from pages")
def sf_string(s, d):
    p = _table(s, d, "pages")
    return p.select(
        "page_id", F.parse_url("url", F.lit("HOST")).alias("host"), F.regexp_extract("url", "/([a-z]{2})/", 1).alias("lang"),
        F.size(F.regexp_extract_all("html", F.lit('<a href="([^"]+)"'), 1)).cast("bigint").alias("links"), F.upper(F.left("url", F.lit(4))).alias("scheme"),
        F.levenshtein(F.left("url", F.lit(20)), F.left("html", F.lit(20))).cast("bigint").alias("far"), F.split("url", "/")[2].alias("third"),
    )


@op("select o_orderkey, date_diff('day', cast(o_orderdate as date), date '2002-01-01') age, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') as mon, strftime(o_orderdate + interval 1 month, '%Y-%m-%d') nxt, cast(quarter(o_orderdate) as bigint) q from orders")
def sf_date(s, d):
    day = F.col("o_orderdate")
    return _table(s, d, "orders").select("o_orderkey", F.date_diff(F.lit("2002-01-01").cast("date"), day).cast("bigint").alias("age"), F.date_format(F.date_trunc("month", day), "yyyy-MM-dd").alias("mon"), F.date_format(day + F.make_interval(months=F.lit(1)), "yyyy-MM-dd").alias("nxt"), F.quarter(day).cast("bigint").alias("q"))


@op("select epoch(time_bucket(interval 6 hours, ts))::bigint as bucket, event_type, count(*) events from events group by 1, 2")
def sf_window(s, d):
    """Tumbling windows of six hours, by their start in seconds."""
    e = _table(s, d, "events").select(F.col("ts").cast("timestamp").alias("ts"), "event_type")
    got = e.groupBy(F.window("ts", "6 hours"), "event_type").agg(F.count("*").alias("events"))
    return got.select(F.unix_timestamp("window.start").alias("bucket"), "event_type", "events")


@op("select p_partkey, md5(cast(p_partkey as varchar)) m, p_partkey % 7 r, cast(abs(round(p_retailprice * 100) - 90000) as bigint) gap, sha256(p_name) sha, round(sqrt(p_size), 6) root from part")
def sf_math_hash(s, d):
    return _table(s, d, "part").select("p_partkey", F.md5(F.col("p_partkey").cast("string")).alias("m"), F.pmod("p_partkey", F.lit(7)).alias("r"), F.abs(F.round(F.col("p_retailprice") * 100) - 90000).cast("bigint").alias("gap"), F.sha2("p_name", 256).alias("sha"), F.round(F.sqrt("p_size"), 6).alias("root"))


_ARRAYS = "select e.src, e.dst, a.n na, b.n nb from e join (select u, list_sort(list(w)) n from h group by u) a on a.u = e.src join (select u, list_sort(list(w)) n from h group by u) b on b.u = e.dst"


@op(f"{_STRONG}, h as (select src u, dst w from e union all select dst, src from e), k as ({_ARRAYS}) select src, dst, len(list_intersect(na, nb)) common, len(list_distinct(list_concat(na, nb))) either, len(list_filter(na, lambda x: x > src)) above, cast(list_sum(list_transform(nb, lambda x: x % 10)) as bigint) digits, list_contains(na, dst) adjacent, cast(len(na) + len(nb) as bigint) held from k")
def sf_array(s, d):
    """Neighbour lists of an edge's ends under the array functions."""
    g = G.copart_strong(s, d)
    lists = g.half_edges().groupBy("u").agg(F.array_sort(F.collect_set("v")).alias("n"))
    k = g.edges.join(lists.select(F.col("u").alias("src"), F.col("n").alias("na")), "src").join(lists.select(F.col("u").alias("dst"), F.col("n").alias("nb")), "dst")
    size = lambda c: F.size(c).cast("bigint")
    return k.select("src", "dst", size(F.array_intersect("na", "nb")).alias("common"), size(F.array_union("na", "nb")).alias("either"), size(F.filter("na", lambda x: x > F.col("src"))).alias("above"), F.aggregate(F.transform("nb", lambda x: x % 10), F.lit(0).cast("bigint"), lambda a, x: a + x).alias("digits"), F.exists("na", lambda x: x == F.col("dst")).alias("adjacent"), size(F.flatten(F.array("na", "nb"))).alias("held"))


@op("select p_partkey, i, x from (select p_partkey, generate_subscripts(l, 1) i, unnest(l) x from (select p_partkey, [p_size, p_size * 10, p_size * 20, p_size * 30] l from part))")
def sf_array_rows(s, d):
    sizes = F.transform(F.array(*[F.lit(k) for k in (1, 10, 20, 30)]), lambda k: k * F.col("p_size"))
    lists = _table(s, d, "part").select("p_partkey", sizes.alias("l"))
    return lists.select("p_partkey", F.posexplode("l").alias("i", "x")).select("p_partkey", (F.col("i") + 1).alias("i"), "x")


@op("select o_orderstatus, o_orderpriority as p, count(*) n from orders group by 1, 2")
def sf_map(s, d):
    """Counts kept as one map for each status, merged with an equal map, and taken apart again."""
    n = _table(s, d, "orders").groupBy("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))
    m = n.groupBy("o_orderstatus").agg(F.map_from_entries(F.collect_list(F.struct("o_orderpriority", "n"))).alias("m"))
    both = m.select("o_orderstatus", F.map_zip_with("m", "m", lambda k, a, b: (a + b) / 2).alias("m"))
    return both.select("o_orderstatus", F.explode("m").alias("p", "n")).select("o_orderstatus", "p", F.col("n").cast("bigint").alias("n"))


@op("select event_id, cast(json_extract(props, '$.k') as bigint) k, '{\"id\":' || event_id || '}' as js from events")
def sf_json(s, d):
    e = _table(s, d, "events")
    return e.select("event_id", F.get_json_object("props", "$.k").cast("bigint").alias("k"), F.to_json(F.struct(F.col("event_id").alias("id"))).alias("js"))


@op("select event_id, cast(json_extract(props, '$.k') as bigint) k from events")
def sf_variant(s, d):
    return _table(s, d, "events").select("event_id", F.variant_get(F.parse_json("props"), "$.k", "bigint").alias("k"))


@op("select x.vec_id a, y.vec_id b, round(sqrt(list_sum(list_transform(generate_series(1, 64), lambda i: (x.embedding[i]::double - y.embedding[i]::double) ** 2))), 6) gap, round(list_inner_product(x.embedding::double[], y.embedding::double[]), 6) product from embeddings x join embeddings y on y.vec_id = x.vec_id + 1")
def sf_vector(s, d):
    """Distance and product of neighbouring rows' vectors."""
    v = _table(s, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("x"))
    both = v.join(v.select((F.col("vec_id") - 1).alias("vec_id"), F.col("vec_id").alias("b"), F.col("x").alias("y")), "vec_id")
    fold = lambda f: F.aggregate(F.zip_with("x", "y", f), F.lit(0.0), lambda a, z: a + z)
    return both.select(F.col("vec_id").alias("a"), "b", F.round(F.sqrt(fold(lambda p, q: (p - q) * (p - q))), 6).alias("gap"), F.round(fold(lambda p, q: p * q), 6).alias("product"))


@op("select o_orderkey, cast(cast(round(o_totalprice * 100) as bigint) as varchar) cents, cast(date_diff('day', cast(o_orderdate as date), date '2002-01-01') as bigint) as age_days from orders")
def sf_decimal_interval(s, d):
    o = _table(s, d, "orders")
    cents = (F.round(F.col("o_totalprice") * 100).cast("decimal(18,2)")).cast("decimal(18,0)").cast("string")
    span = F.lit("2002-01-01").cast("date") - F.col("o_orderdate").cast("date")
    return o.select("o_orderkey", cents.alias("cents"), F.extract(F.lit("DAY"), span).cast("bigint").alias("age_days"))


# ---- extensions -------------------------------------------------------------------------------


@op(f"{_NATION} select src, dst, src || '-' || dst as edge_id, src * 1000 + dst as code from e")
def ux_edge_id(s, d):
    """A vectorised function of its own beside a built-in expression."""
    return G.nation_trade(s, d).edges.select("src", "dst", X.edge_id("src", "dst").alias("edge_id"), X.edge_code("src", "dst").alias("code"))


@op(f"{_NT}, r as (select v.sg, degree, row_number() over (partition by v.sg order by degree) i, count(*) over (partition by v.sg) n from dg join v on dg.vid = v.vid) select sg, round(sum((2 * i - n - 1) * degree)::double / (max(n) * sum(degree)), 6) gini from r group by sg")
def ux_gini_degree(s, d):
    """An aggregate of its own: how unevenly degrees are spread in a subgraph."""
    g = G.nation_trade(s, d)
    return T.degrees(g).join(g.vertices, "vid").groupBy("sg").agg(F.round(X.gini("degree"), 6).alias("gini"))


@op(f"{_STRONG} select x.src vid, x.dst a, y.dst b from e x join e y on x.src = y.src and x.dst < y.dst")
def ux_neighbour_pairs(s, d):
    """A table function of its own: pairs of larger neighbours."""
    s.udtf.register("neighbour_pairs", X.NeighbourPairs)
    e = G.copart_strong(s, d).edges
    e.groupBy(F.col("src").alias("vid")).agg(F.array_sort(F.collect_list("dst")).alias("nbrs")).createOrReplaceTempView("neighbour_lists")
    return s.sql("select p.vid, p.a, p.b from neighbour_lists l, lateral neighbour_pairs(l.vid, l.nbrs) p")


def queries() -> dict[str, Query]:
    return {name: f for name, (f, _) in _FOUND.items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for name, (_, sql) in _FOUND.items() if sql}
