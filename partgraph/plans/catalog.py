"""Queries of the graph methods, and the SQL that gives the same rows."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import clustering as K
from ..operators import forest as M
from ..operators import partitions as P
from ..operators import traversal as V
from ..operators import triangles as T
from ..operators.bsp import MessageLog, Phase, all_vote, send, send_to_all
from ..operators.components import connected_components
from ..sources import graphs as G
from ..sources.graphs import GRAPHS, PartitionedGraph

Query = Callable[[SparkSession, str], DataFrame]

#: CTEs e (src, dst, weight) and v (vid, sg) of each graph.
_PAIRS = "select x.{k} src, y.{k} dst, count(*) n from lineitem x join lineitem y on x.l_orderkey = y.l_orderkey and x.{k} < y.{k} group by all"
_PART = "v as (select p_partkey vid, cast(regexp_extract(p_brand, '(\\d+)$', 1) as bigint) sg from part)"
_CENTS = "cast(round(p_retailprice * 100) as bigint)"
_LANG = "coalesce(list_position(['en', 'fr', 'de', 'es'], regexp_extract(url, '/([a-z]{2})/', 1)), 0)"


def _copart_sql(support: int) -> str:
    return f"e as (select src, dst, abs(a.c - b.c) weight from ({_PAIRS.format(k='l_partkey')}) p join (select p_partkey, {_CENTS} c from part) a on src = a.p_partkey join (select p_partkey, {_CENTS} c from part) b on dst = b.p_partkey where n >= {support}), {_PART}"


_CITE = "po as (select distinct l_partkey, o_orderkey, o_orderdate from lineitem join orders on l_orderkey = o_orderkey), back as (select o_orderkey, o_orderdate, lag(o_orderkey, 1) over w k1, lag(o_orderdate, 1) over w d1, lag(o_orderkey, 2) over w k2, lag(o_orderdate, 2) over w d2 from po window w as (partition by l_partkey order by o_orderdate, o_orderkey)), arrows as (select o_orderkey s, k1 d, date_diff('day', cast(d1 as date), cast(o_orderdate as date)) weight from back where k1 is not null union all select o_orderkey, k2, date_diff('day', cast(d2 as date), cast(o_orderdate as date)) from back where k2 is not null)"
_CITE_E = f"{_CITE}, e as (select least(s, d) src, greatest(s, d) dst, min(weight) weight from arrows where s <> d group by 1, 2)"
CTE = {
    "copart": _copart_sql(1),
    "copart_strong": _copart_sql(2),
    "cosupp": f"e as (select src, dst, 1000000 // n weight from ({_PAIRS.format(k='l_suppkey')})), v as (select s_suppkey vid, cast(s_nationkey as bigint) sg from supplier)",
    "nation": "e as (select cast(least(c_nationkey, s_nationkey) as bigint) src, cast(greatest(c_nationkey, s_nationkey) as bigint) dst, 1000000 // count(*) weight from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join supplier on l_suppkey = s_suppkey where c_nationkey <> s_nationkey group by 1, 2), v as (select cast(n_nationkey as bigint) vid, cast(n_regionkey as bigint) sg from nation)",
    "order_cite": f"{_CITE_E}, v as (select o_orderkey vid, cast(year(o_orderdate) as bigint) sg from orders)",
    "order_range": f"{_CITE_E}, v as (select o_orderkey vid, o_orderkey * 8 // (select max(o_orderkey) + 1 from orders) sg from orders)",
    "page_colink": f"links as (select distinct page_id, rtrim(href, '.,') href from (select page_id, unnest(regexp_extract_all(html, '<a href=\"([^\"]+)\"', 1)) href from pages)), e as (select x.page_id src, y.page_id dst, 1000 // count(*) weight from links x join links y on x.href = y.href and x.page_id < y.page_id group by 1, 2), v as (select page_id vid, cast({_LANG} as bigint) sg from pages)",
    "user_coact": "acts as (select user_id, event_type, date_trunc('hour', ts) w, count(*) n from events group by all), e as (select x.user_id src, y.user_id dst, cast(1000000 // sum(x.n * y.n) as bigint) weight from acts x join acts y on x.event_type = y.event_type and x.w = y.w and x.user_id < y.user_id group by 1, 2), v as (select distinct user_id vid, user_id % 4 sg from events)",
    "cust_part": "e as (select o_custkey src, l_partkey + 1000000000 dst, 1000000 // count(*) weight from lineitem join orders on l_orderkey = o_orderkey group by 1, 2), v as (select c_custkey vid, cast(c_nationkey as bigint) sg from customer union all select p_partkey + 1000000000, 100 + cast(regexp_extract(p_brand, '(\\d+)$', 1) as bigint) from part)",
    "conv_next": "turns as (select distinct conv_id, conv_id * 10000 + turn vid from conversations), e as (select a.vid src, b.vid dst, cast(1 as bigint) weight from turns a join turns b on b.vid = a.vid + 1), v as (select vid, conv_id sg from turns)",
    "emb_knn": "dist as (select x.vec_id s, y.vec_id d, sqrt(list_sum(list_transform(generate_series(1, 64), lambda i: (x.embedding[i]::double - y.embedding[i]::double) ** 2))) r from embeddings x join embeddings y on x.vec_id <> y.vec_id), near as (select s, d, r from dist qualify row_number() over (partition by s order by r, d) <= 8), e as (select least(s, d) src, greatest(s, d) dst, min(cast(round(r * 1e6) as bigint)) weight from near group by 1, 2), v as (select vec_id vid, cast(label as bigint) sg from embeddings)",
}
_TRI = ", t as (select x.src a, x.dst b, y.dst c from e x join e y on x.dst = y.src join e z on z.src = x.src and z.dst = y.dst)"
_TYPED = _TRI + ", tt as (select a, b, c, p.sg pa, q.sg pb, r.sg pc, case when p.sg = q.sg and q.sg = r.sg then 'i' when p.sg = q.sg or q.sg = r.sg or p.sg = r.sg then 'ii' else 'iii' end tri_type from t join v p on a = p.vid join v q on b = q.vid join v r on c = r.vid)"
_OWNED = ", o as (select src, dst, weight, p.sg ps, q.sg qs from e join v p on src = p.vid join v q on dst = q.vid)"
_DEG = ", dg as (select vid, count(*) degree from (select src vid from e union all select dst from e) group by vid)"
_HALF = ", h as (select src u, dst w, weight from e union all select dst, src, weight from e)"
_PT_STATS = _OWNED + ", s as (select ps sg, ps <> qs cut from o union all select qs, true from o where ps <> qs), st as (select v.sg, any_value(n) vertices, count(*) filter (not cut) inner_edges, count(*) filter (cut) cut_edges from (select sg, count(*) n from v group by sg) v left join s on v.sg = s.sg group by v.sg)"
_META = _OWNED + ", mg as (select least(ps, qs) src_sg, greatest(ps, qs) dst_sg, count(*) cut_edges from o where ps <> qs group by 1, 2)"
#: Least label that reaches each vertex; the state of the recursion is one row for each vertex.
_COMP = _HALF + ", cc(vid, comp) using key (vid) as (select vid, vid from v union select h.w, min(cc.comp) from cc join h on cc.vid = h.u join recurring.cc old on old.vid = h.w where cc.comp < old.comp group by h.w)"


def _bfs(k: int, seed: int = 7, round_: int = 0, name: str = "lab") -> str:
    """CTEs: centres, and the least (dist, rank) of each vertex they reach; visited (rank, vertex) pairs are not revisited."""
    return (
        f", {name}_c as (select vid, cast(row_number() over (order by md5('{seed}:{round_}:' || vid), vid) - 1 as int) r from v qualify r < {k})"
        f", {name}_l(r, vid, d) using key (r, vid) as (select r, vid, 0 from {name}_c union select l.r, h.w, min(l.d) + 1 from {name}_l l join h on l.vid = h.u left join recurring.{name}_l old on old.r = l.r and old.vid = h.w where old.vid is null group by l.r, h.w)"
        f", {name} as (select vid, cast(min(d) as int) dist, cast(arg_min(r, d * 1000 + r) as int) centre_rank from {name}_l group by vid)"
    )


def _cut(name: str = "lab") -> str:
    return f"from o left join {name} p on src = p.vid left join {name} q on dst = q.vid where p.centre_rank is distinct from q.centre_rank"


#: Cycle rule: an edge is in the forest if its ends are not joined by lesser edges.
_MSF = ", re as (select *, row_number() over (order by weight, src, dst) r from e), rh as (select src u, dst w, r from re union all select dst, src, r from re), reach(r, vid) as (select r, src from re union select k.r, rh.w from reach k join rh on rh.u = k.vid and rh.r < k.r), f as (select src, dst, weight from re where not exists (select 1 from reach where reach.r = re.r and reach.vid = re.dst))"

#: Partitions of a graph: name -> (method, SQL that replaces the owner).
PARTITIONS = {
    "hash8": (lambda g: P.partition_hash(g, 8), "cast('0x' || substr(md5(cast(vid as varchar)), 1, 8) as bigint) % 8"),
    "range8": (lambda g: P.partition_range(g, 8), "vid * 8 // (select max(vid) + 1 from v)"),
    "single": (P.partition_single, "cast(0 as bigint)"),
    "singletons": (P.partition_singletons, "vid"),
    "halves": (lambda g: P.partition_range(g, 2), "vid * 2 // (select max(vid) + 1 from v)"),
}


def _repart(cte: str, sql: str) -> str:
    """The CTEs of a graph with its vertices under another owner."""
    head, _, tail = cte.rpartition("v as (")
    return f"{head}v0 as ({tail.replace('from v)', 'from v0)')}, v as (select vid, {sql.replace('from v)', 'from v0)')} sg from v0)"


def _count(name: str, method) -> Query:
    return lambda s, d: method(GRAPHS[name](s, d)).agg(F.count("*").alias("triangles"))


def _log(spark: SparkSession, log: list[dict], *columns: str) -> DataFrame:
    schema = ", ".join(f"{c} {'string' if c == 'phase' else 'bigint'}" for c in columns)
    return spark.createDataFrame([tuple(r[c] for c in columns) for r in log], schema)


def _on(name: str, method) -> Query:
    """A query that applies ``method`` to a graph."""
    return lambda s, d: method(GRAPHS[name](s, d))


def _labels(unit: str, k: int = 4):
    return lambda g: K.assign(g, K.draw_centres(g, k), unit)[0]


def _kway_row(g: PartitionedGraph, k: int, percent: int, unit: str, rounds: int = 3, strict: bool = False) -> DataFrame:
    """Summary of a run whose threshold is a share of the edges."""
    g = g.stored()
    tau = g.edges.count() * percent // 100
    row = K.kway_cluster(g, k, tau, max_rounds=rounds, unit=unit, strict=strict)[1]
    return _log(g.edges.sparkSession, [row | {"tau": tau, "ok": int(row["accepted"])}], "tau", "round", "rounds", "cut", "ok")


def _steps(g: PartitionedGraph, k: int = 4) -> DataFrame:
    """(unit, supersteps, messages) of the labels, beside the meta-graph's diameter and the largest distance."""
    g = g.stored()
    centres = K.draw_centres(g, k)
    rows = []
    for unit in ("vertex", "subgraph"):
        log = MessageLog()
        labels, n = K.assign(g, centres, unit, log=log)
        rows.append((unit, n, sum(x[4] for x in log.steps), labels.agg(F.max("dist")).first()[0]))
    table = g.edges.sparkSession.createDataFrame(rows, "unit string, supersteps bigint, messages bigint, max_dist bigint")
    return table.crossJoin(P.meta_diameter(g).select("meta_diameter"))


def _votes(g: PartitionedGraph) -> DataFrame:
    """(superstep, phase, active, msgs_local, msgs_remote) of one exchange: every subgraph tells all others its size, cut
    edges are sent, and the master hears whether all subgraphs are idle (an edge phase) or not."""
    spark, log = g.edges.sparkSession, MessageLog()
    send(send_to_all(g.vertices.groupBy("sg").agg(F.count("*").alias("n")), g.vertices), log, Phase.DRAW, F.col("sg") != F.col("to_sg"))
    sent = send(g.owned_edges().select(F.col("src_sg").alias("sg"), "dst_sg", "src", "dst"), log, Phase.EXCHANGE, F.col("sg") != F.col("dst_sg"))
    log.add(Phase.DONE if all_vote(sent.where("sg <> dst_sg"), g.vertices) else Phase.EXCHANGE, 0)
    return log.table(spark)


def _truss_sql(name: str, k: int, rounds: int) -> str:
    """Peeling written out: each round keeps the edges in k - 2 triangles of those left; later rounds change nothing."""
    out = f"with {CTE[name]}, e0 as (select src, dst from e)"
    for r in range(rounds):
        t = f"t{r} as (select x.src a, x.dst b, y.dst c from e{r} x join e{r} y on x.dst = y.src join e{r} z on z.src = x.src and z.dst = y.dst)"
        out += f", {t}, e{r + 1} as (select src, dst from (select a src, b dst from t{r} union all select a, c from t{r} union all select b, c from t{r}) group by 1, 2 having count(*) >= {k - 2})"
    return f"{out} select src, dst from e{rounds}"


def _rank_sql(name: str, rounds: int = 5) -> str:
    out = f"with {CTE[name]}{_HALF}{_DEG}, k as (select count(*) n from v), p0 as (select vid, {V.UNIT} // n score from v, k)"
    for r in range(rounds):
        out += f", g{r} as (select h.w vid, cast(sum(score // degree) as bigint) got from h join dg on dg.vid = h.u join p{r} on p{r}.vid = h.u group by h.w), p{r + 1} as (select v.vid, coalesce(got, 0) * 85 // 100 + {V.UNIT * 15} // (100 * n) score from v left join g{r} on v.vid = g{r}.vid, k)"
    return out


def _between_sql(name: str, sources: list[int], steps: int) -> str:
    """Path counts level by level, then pair dependencies by definition: paths through v among all of s to t."""
    src = ", ".join(f"({s})" for s in sources)
    out = f"with {CTE[name]}{_HALF}, d0 as (select vid s, vid, 0 d, 1.0::double paths from v)"
    for r in range(1, steps + 1):
        seen = " union all ".join(f"select s, vid from d{i}" for i in range(r))
        out += f", d{r} as (select s, h.w vid, {r} d, sum(paths) paths from d{r - 1} join h on h.u = vid where (s, h.w) not in (select (s, vid) from ({seen})) group by 1, 2)"
    every = " union all ".join(f"select * from d{i}" for i in range(steps + 1))
    return f"{out}, al as ({every}) select v.vid, round(coalesce(sum(a.paths * b.paths / st.paths), 0), 6) score from al st join al a on a.s = st.s and a.vid <> st.s join al b on b.s = a.vid and b.vid = st.vid and a.vid <> st.vid and a.d + b.d = st.d right join (select distinct vid from al where s in (select * from (values {src})) and vid <> s) v on v.vid = a.vid and st.s in (select * from (values {src})) group by v.vid"


#: Graphs for which only edges, types, messages and partition statistics are registered.
SIDE = ("order_range", "user_coact", "cust_part", "conv_next", "emb_knn")
LISTED = ("nation", "copart_strong", "order_cite")
FEW = ("nation", "cosupp", "copart_strong")
CLUSTERED = ("nation", "cosupp", "copart", "copart_strong", "order_cite", "page_colink")
SHAPED = ("nation", "copart_strong")
RUN_GRID = [(2, 30), (4, 50), (8, 90), (16, 90)]


def queries() -> dict[str, Query]:
    out: dict[str, Query] = {}
    for name, g in GRAPHS.items():
        out[f"g_{name}_edges"] = lambda s, d, g=g: g(s, d).edges
        out[f"pt_stats_{name}"] = _on(name, P.partition_stats)
        out[f"tri_msgs_{name}"] = _on(name, T.message_counts)
        out[f"tri_per_type_{name}"] = _on(name, T.count_types)
        if name in SIDE:
            continue
        out[f"pt_shape_{name}"] = _on(name, P.graph_shape)
        out[f"tri_vertex_centric_{name}"] = _on(name, T.count_vertex_centric)
        out[f"tri_subgraph_{name}"] = _on(name, lambda g: T.count_types(g).agg(F.coalesce(F.sum("triangles"), F.lit(0)).alias("triangles")))
        out[f"tri_kernel_{name}"] = _on(name, T.count_kernel)
        out[f"tri_placement_{name}"] = _on(name, T.type2_placement)
        out[f"tri_probes_{name}"] = _on(name, T.probes)
        out[f"transitivity_{name}"] = _on(name, T.transitivity)
        out[f"components_{name}"] = _on(name, lambda g: connected_components(g.edges).groupBy("comp").agg(F.count("*").alias("vertices")))
        out[f"degree_histogram_{name}"] = _on(name, lambda g: T.degrees(g).groupBy("degree").agg(F.count("*").alias("vertices")))
        out[f"pt_meta_graph_{name}"] = _on(name, P.meta_graph)
    out["transitivity_page_colink"] = lambda s, d: T.transitivity_of_sets(G.page_links(s, d).toDF("vid", "item"))
    for name in LISTED:
        out[f"tri_list_{name}"] = _on(name, T.triangles)
        out[f"tri_kernel_list_{name}"] = _on(name, T.triangles_kernel)
        out[f"tri_bsp_complete_{name}"] = _count(name, lambda x: T.triangles_bsp(x)[0])
        out[f"tri_bsp_pruned_{name}"] = _count(name, lambda x: T.triangles_bsp(x, prune=True)[0])
        out[f"tri_printed_{name}"] = _count(name, lambda x: T.triangles_bsp(x, "as_printed")[0])
        out[f"tri_receive_check_{name}"] = _count(name, lambda x: T.triangles_bsp(x, "receive_check")[0])
        out[f"tri_node_iterator_{name}"] = _count(name, T.triangles_node_iterator)
        out[f"tri_forward_{name}"] = _count(name, T.triangles_forward)
        out[f"tri_colour_{name}"] = _count(name, T.triangles_colour)
        out[f"tri_recall_{name}"] = _on(name, T.triangle_recall)
        out[f"tri_supersteps_{name}"] = lambda s, d, g=GRAPHS[name]: _log(s, T.triangles_bsp(g(s, d))[1], "superstep", "found", "messages")
        out[f"tri_vertex_supersteps_{name}"] = lambda s, d, g=GRAPHS[name]: _log(s, T.triangles_vertex_supersteps(g(s, d)), "superstep", "found", "messages")
        out[f"tri_msgs_pruned_{name}"] = _on(name, lambda g: T.sent_pairs(T._owned(g)[1]).agg(F.count("*").alias("messages")))
        out[f"tri_open_wedges_{name}"] = _on(name, lambda g: T.open_wedges(g).agg(F.count("*").alias("open_wedges")))
        out[f"tri_per_vertex_{name}"] = _on(name, lambda g: T.per_vertex(T.triangles(g)))
        out[f"tri_per_edge_{name}"] = _on(name, lambda g: T.per_edge(T.triangles(g)))
        out[f"tri_estimate_{name}"] = _on(name, T.triangles_estimate)
        out[f"orient_degree_{name}"] = _on(name, lambda g: T.orient(g, "degree"))
        out[f"clustering_coefficient_{name}"] = _on(name, T.clustering_coefficient)
    for name, form in (("tri_list", T.triangles), ("tri_kernel_list", T.triangles_kernel)):
        out[f"{name}_page_colink"] = lambda s, d, f=form: T.triangles_of_sets(G.page_colink(s, d), G.page_links(s, d).toDF("vid", "item"), f)
    out["k_truss_4_copart_strong"] = _on("copart_strong", lambda g: T.k_truss(g, 4))
    out["k_truss_5_nation"] = _on("nation", lambda g: T.k_truss(g, 5))
    for part, (method, _) in PARTITIONS.items():
        for name in ("copart_strong", "order_cite"):
            out[f"tri_per_type_{name}_{part}"] = _on(name, lambda g, m=method: T.count_types(m(g)))
            out[f"tri_msgs_{name}_{part}"] = _on(name, lambda g, m=method: T.message_counts(m(g)))
        out[f"pt_stats_copart_strong_{part}"] = _on("copart_strong", lambda g, m=method: P.partition_stats(m(g)))
    for p in (1, 2, 4, 8, 25):
        out[f"tri_types_copart_hash{p}"] = _on("copart", lambda g, p=p: T.count_kernel(P.partition_hash(g, p)))
        out[f"pt_shape_copart_hash{p}"] = _on("copart", lambda g, p=p: P.graph_shape(P.partition_hash(g, p)))
    for name in ("copart_strong", "conv_next"):
        out[f"tri_supersteps_components_{name}"] = lambda s, d, g=GRAPHS[name]: _log(s, T.triangles_bsp(P.partition_components(g(s, d)))[1], "superstep", "found", "messages")
        out[f"pt_components_{name}"] = _on(name, lambda g: P.partition_stats(P.partition_components(g)))
    out["tri_supersteps_halves_order_cite"] = lambda s, d: _log(s, T.triangles_bsp(P.partition_range(GRAPHS["order_cite"](s, d), 2))[1], "superstep", "found", "messages")
    out["pt_components_in_partition_copart_strong"] = _on("copart_strong", lambda g: P.assign_subgraphs(g).vertices)
    out["pt_label_prop_copart_strong"] = _on("copart_strong", lambda g: P.partition_stats(P.partition_lp(g, 8)))
    out["pt_label_prop_order_cite"] = _on("order_cite", lambda g: P.partition_stats(P.partition_lp(g, 8)))
    out["pt_kway_copart_strong"] = _on("copart_strong", lambda g: P.partition_stats(P.partition_kway(g, 8)))
    for name in ("nation", "order_cite", "page_colink"):
        out[f"pt_meta_diameter_{name}"] = _on(name, P.meta_diameter)
    out["symmetrize_cite"] = lambda s, d: G.symmetrize(G.order_cite_arrows(s, d).withColumn("weight", F.lit(1).cast("bigint"))).select("src", "dst")
    out["size_arrows_cite"] = lambda s, d: G.symmetrize(G.order_cite_arrows(s, d).withColumn("weight", F.lit(1))).agg(F.count("*").alias("edges"), (2 * F.count("*")).alias("arrows"))

    for name in CLUSTERED:
        out[f"kw_centres_{name}"] = _on(name, lambda g: K.draw_centres(g, 4))
        for unit in ("vertex", "subgraph"):
            out[f"kw_labels_{unit}_{name}"] = _on(name, _labels(unit))
        out[f"kw_cut_{name}"] = _on(name, lambda g: K.edge_cut(g, _labels("vertex")(g)))
    for name in SHAPED:
        out[f"kw_centres_per_subgraph_{name}"] = _on(name, lambda g: K.draw_centres(g, 4, sampling="per_subgraph"))
        out[f"kw_profile_{name}"] = _on(name, lambda g: K.cluster_summary(g, _labels("vertex")(g)))
        out[f"kw_check_{name}"] = _on(name, lambda g: K.check_clusters(g, _labels("subgraph")(g)))
        out[f"kw_supersteps_{name}"] = _on(name, _steps)
    out["kw_exchange_nation"] = _on("nation", lambda g: K.draw_exchange(g, 4))
    out["kw_exchange_copart"] = _on("copart", lambda g: K.draw_exchange(g, 4))
    out["kw_weighted_nation"] = _on("nation", lambda g: K.assign_weighted(g, K.draw_centres(g, 4)))
    out["kw_weighted_copart_strong"] = _on("copart_strong", lambda g: K.assign_weighted(g, K.draw_centres(g, 4)))
    for k, percent in RUN_GRID:
        out[f"kw_run_copart_strong_k{k}_tau{percent}"] = _on("copart_strong", lambda g, k=k, p=percent: _kway_row(g, k, p, "vertex"))
    for unit in ("vertex", "subgraph"):
        out[f"kw_run_{unit}_order_cite"] = _on("order_cite", lambda g, u=unit: _kway_row(g, 4, 50, u))
        out[f"kw_run_{unit}_page_colink"] = _on("page_colink", lambda g, u=unit: _kway_row(g, 4, 50, u))
    out["kw_run_never_met_nation"] = _on("nation", lambda g: _kway_row(g, 4, 0, "subgraph", strict=True))
    out["bsp_votes_nation"] = _on("nation", _votes)

    for name in FEW:
        for unit in ("vertex", "subgraph", "single", "filter"):
            out[f"msf_{unit}_{name}"] = _on(name, lambda g, u=unit: M.spanning_forest(g, u)[0].select("src", "dst", "weight"))
        out[f"msf_summary_{name}"] = _on(name, lambda g: M.forest_summary(g, M.spanning_forest(g, finish=M.FINISH_EDGES)[0]))
        out[f"msf_trees_{name}"] = _on(name, lambda g: M.spanning_forest(g)[1])
        out[f"single_linkage_{name}"] = _on(name, lambda g: M.single_linkage(g, M.spanning_forest(g, finish=M.FINISH_EDGES)[0], 3))
    for name in (*FEW, "order_cite"):
        out[f"msf_rounds_{name}"] = lambda s, d, g=GRAPHS[name]: _log(s, M.spanning_forest(g(s, d))[2], "round", "phase", "asks", "jumps")
        out[f"msf_vertex_rounds_{name}"] = lambda s, d, g=GRAPHS[name]: _log(s, M.spanning_forest(g(s, d), "vertex")[2], "round", "phase", "asks", "jumps")
    for name in SHAPED:
        out[f"msf_literal_halt_{name}"] = _on(name, lambda g: M.forest_summary(g, M.spanning_forest(g, literal_halt=True)[0]))
        out[f"msf_local_edges_{name}"] = _on(name, lambda g: M.forest_summary(g, M.local_forest(g).where("is_edge")))
    for name in ("copart", "order_cite", "emb_knn", "conv_next"):
        out[f"msf_summary_{name}"] = _on(name, lambda g: M.forest_summary(g, M.spanning_forest(g, finish=M.FINISH_EDGES)[0]).select("edges", "trees"))

    for name in SHAPED:
        out[f"bfs_from_0_{name}"] = _on(name, lambda g: V.sssp(g, 0))
        out[f"bfs_subgraph_from_0_{name}"] = _on(name, lambda g: V.sssp(g, 0, "subgraph"))
        out[f"reachable_{name}"] = _on(name, lambda g: V.reachable(g, [0, 1]))
        out[f"pagerank_{name}"] = _on(name, V.pagerank)
        out[f"subgraph_rank_{name}"] = _on(name, V.subgraph_rank)
        out[f"coarsen_{name}"] = _on(name, lambda g: V.coarsen(g).edges)
    out["betweenness_nation"] = _on("nation", lambda g: V.betweenness(g, [0, 1, 2]))
    out["betweenness_user_coact"] = _on("user_coact", lambda g: V.betweenness(g, [0, 1, 2]))
    return out


def oracle_sql() -> dict[str, str]:
    out: dict[str, str] = {}
    shape = "select cast(sum(vertices) as bigint) n, cast(sum(cut_edges) // 2 + sum(inner_edges) as bigint) m, cast(2 * (sum(cut_edges) // 2 + sum(inner_edges)) as bigint) arrows, (select coalesce(max(degree), 0) from dg) d_max, count(*) p, max(vertices) l_max, max(cut_edges) r_max, cast(sum(cut_edges) // 2 as bigint) cut, cast(max(vertices) * count(*) * 100 // sum(vertices) - 100 as bigint) excess from st"
    msgs = "select 'vertex' form, 1 round, count(*) messages from o union all select 'vertex', 2, count(*) from e x join e y on x.dst = y.src union all select 'subgraph', 1, count(*) from o where ps <> qs union all select 'subgraph', 2, count(*) from o x join o y on x.dst = y.src where x.ps <> x.qs and y.ps <> y.qs and x.ps <> y.qs"
    per_type = "select tri_type, count(*) triangles from tt group by tri_type"
    wedges = "(select coalesce(sum(degree * (degree - 1) // 2), 0) from dg)"
    for name, cte in CTE.items():
        w = f"with {cte}"
        out[f"g_{name}_edges"] = f"{w} select src, dst, weight from e"
        out[f"pt_stats_{name}"] = f"{w}{_PT_STATS} select * from st"
        out[f"pt_shape_{name}"] = f"{w}{_PT_STATS}{_DEG} {shape}"
        out[f"tri_msgs_{name}"] = f"{w}{_OWNED} {msgs}"
        out[f"tri_per_type_{name}"] = out[f"tri_kernel_{name}"] = f"{w}{_TYPED} {per_type}"
        out[f"tri_vertex_centric_{name}"] = out[f"tri_subgraph_{name}"] = f"{w}{_TRI} select count(*) triangles from t"
        out[f"tri_placement_{name}"] = f"{w}{_TYPED} select case when pb = pc then 'first' when pa = pc then 'middle' else 'last' end away, count(*) triangles from tt where tri_type = 'ii' group by 1"
        up = "(select src, dst, case when (a.degree, src) < (b.degree, dst) then src else dst end lo, least(a.degree, b.degree) low from e join dg a on a.vid = src join dg b on b.vid = dst)"
        out[f"tri_probes_{name}"] = f"{w}{_OWNED}{_DEG} select 'node_iterator' form, cast(coalesce(sum(n * (n - 1) // 2), 0) as bigint) probes from (select count(*) n from e group by src) union all select 'forward', cast(coalesce(sum(n * (n - 1) // 2), 0) as bigint) from (select count(*) n from {up} group by lo) union all select 'subgraph_kernel', cast(coalesce(sum(low), 0) as bigint) from {up} u join o on u.src = o.src and u.dst = o.dst where ps = qs"
        out[f"transitivity_{name}"] = f"{w}{_TRI}{_DEG} select count(*) triangles, cast({wedges} as bigint) wedges, cast(case when {wedges} > 0 then 3000000 * count(*) // {wedges} end as bigint) transitivity from t"
        out[f"components_{name}"] = f"with recursive {cte}{_COMP} select comp, count(*) vertices from cc where vid in (select u from h) group by comp"
        out[f"degree_histogram_{name}"] = f"{w}{_DEG} select degree, count(*) vertices from dg group by degree"
        out[f"pt_meta_graph_{name}"] = f"{w}{_META} select * from mg"
    for name in LISTED:
        w = f"with {CTE[name]}"
        total = f"{w}{_TRI} select count(*) triangles from t"
        out[f"tri_list_{name}"] = out[f"tri_kernel_list_{name}"] = f"{w}{_TYPED} select a, b, c, tri_type from tt"
        for form in ("bsp_complete", "bsp_pruned", "receive_check", "node_iterator", "forward", "colour"):
            out[f"tri_{form}_{name}"] = total
        away = "pb = pc and pa <> pb"
        out[f"tri_printed_{name}"] = f"{w}{_TYPED} select count(*) triangles from tt where not ({away})"
        out[f"tri_recall_{name}"] = f"{w}{_TYPED} select count(*) filter (not ({away})) found, count(*) total, count(*) filter ({away}) missed from tt"
        three = "o x join o y on x.dst = y.src where x.ps <> x.qs and y.ps <> y.qs and x.ps <> y.qs"
        out[f"tri_supersteps_{name}"] = f"{w}{_TYPED}{_OWNED}, r1 as (select count(*) n from o where ps <> qs), r2 as (select count(*) n from {three}) select 0 superstep, (select count(*) from tt where tri_type <> 'iii') found, (select n from r1) messages union all select 1, 0, (select n from r2) from r1 where n > 0 union all select 2, (select count(*) from tt where tri_type = 'iii'), 0 from r2 where n > 0"
        out[f"tri_vertex_supersteps_{name}"] = f"{w}{_TRI} select 0 superstep, 0 found, (select count(*) from e) messages union all select 1, 0, (select count(*) from e x join e y on x.dst = y.src) union all select 2, (select count(*) from t), 0"
        out[f"tri_msgs_pruned_{name}"] = f"{w}{_OWNED} select count(*) messages from o x where ps <> qs and exists (select 1 from o y where y.ps <> y.qs and y.src = x.src and y.dst > x.dst and y.qs <> x.qs)"
        out[f"tri_open_wedges_{name}"] = f"{w}{_OWNED} select count(*) open_wedges from o x join o y on x.dst = y.src left join e z on z.src = x.src and z.dst = y.dst where x.ps <> x.qs and y.ps <> y.qs and x.ps <> y.qs and z.src is null"
        tv = "(select a vid from t union all select b from t union all select c from t)"
        out[f"tri_per_vertex_{name}"] = f"{w}{_TRI} select vid, count(*) triangles from {tv} group by vid"
        out[f"tri_per_edge_{name}"] = f"{w}{_TRI} select src, dst, count(*) triangles from (select a src, b dst from t union all select a, c from t union all select b, c from t) group by 1, 2"
        out[f"tri_estimate_{name}"] = f"{w}, e1 as (select * from e where cast('0x' || substr(md5('7:' || src || ':' || dst), 1, 8) as bigint) % 100 < 50){_TRI.replace('from e x', 'from e1 x').replace('join e y', 'join e1 y').replace('join e z', 'join e1 z')} select (select count(*) from e1) kept_edges, count(*) kept_triangles, count(*) * 1000000 // 125000 estimate from t"
        out[f"orient_degree_{name}"] = f"{w}{_DEG} select case when (a.degree, src) < (b.degree, dst) then src else dst end lo, case when (a.degree, src) < (b.degree, dst) then dst else src end hi from e join dg a on a.vid = src join dg b on b.vid = dst"
        out[f"clustering_coefficient_{name}"] = f"{w}{_TRI}{_DEG}, tv as (select vid, count(*) n from {tv} group by vid) select dg.vid, degree, coalesce(n, 0) triangles, round(2.0::double * coalesce(n, 0) / (degree * (degree - 1)), 6) coefficient from dg left join tv on dg.vid = tv.vid where degree > 1"
    out["k_truss_4_copart_strong"] = _truss_sql("copart_strong", 4, 8)
    out["k_truss_5_nation"] = _truss_sql("nation", 5, 3)
    for part, (_, sql) in PARTITIONS.items():
        for name in ("copart_strong", "order_cite"):
            w = f"with {_repart(CTE[name], sql)}"
            out[f"tri_per_type_{name}_{part}"] = f"{w}{_TYPED} {per_type}"
            out[f"tri_msgs_{name}_{part}"] = f"{w}{_OWNED} {msgs}"
            out[f"pt_stats_{name}_{part}"] = f"{w}{_PT_STATS} select * from st"
    for p in (1, 2, 4, 8, 25):
        w = f"with {_repart(CTE['copart'], PARTITIONS['hash8'][1].replace('% 8', f'% {p}'))}"
        out[f"tri_types_copart_hash{p}"] = f"{w}{_TYPED} {per_type}"
        out[f"pt_shape_copart_hash{p}"] = f"{w}{_PT_STATS}{_DEG} {shape}"
    for name in ("copart_strong", "conv_next"):
        w = f"with recursive {CTE[name]}{_COMP}"
        out[f"tri_supersteps_components_{name}"] = f"with {CTE[name]}{_TRI} select 0 superstep, count(*) found, 0 messages from t"
        out[f"pt_components_{name}"] = f"{w} select comp sg, count(*) vertices, (select count(*) from e join cc x on x.vid = e.src where x.comp = cc.comp) inner_edges, 0 cut_edges from cc group by comp"
    w = f"with {_repart(CTE['order_cite'], PARTITIONS['halves'][1])}"
    out["tri_supersteps_halves_order_cite"] = f"{w}{_TRI}{_OWNED} select 0 superstep, (select count(*) from t) found, (select count(*) from o where ps <> qs) messages union all select 1, 0, 0"
    name = "copart_strong"
    inner = f"with recursive {CTE[name].replace('e as (', 'e0 as (', 1)}, e as (select e0.* from e0 join v p on p.vid = src join v q on q.vid = dst where p.sg = q.sg){_COMP}"
    out["pt_components_in_partition_copart_strong"] = f"{inner} select vid, comp sg from cc"
    for name in ("nation", "order_cite", "page_colink"):
        walk = ", gh as (select src_sg u, dst_sg w from mg union all select dst_sg, src_sg from mg), gd(a, b, hops) using key (a, b) as (select distinct sg, sg, 0 from v union select gd.a, gh.w, min(gd.hops) + 1 from gd join gh on gh.u = gd.b left join recurring.gd old on old.a = gd.a and old.b = gh.w where old.a is null group by 1, 2)"
        out[f"pt_meta_diameter_{name}"] = f"with recursive {CTE[name]}{_META}{walk} select count(distinct a) subgraphs, count(*) filter (hops = 1 and a < b) meta_edges, cast(max(hops) as bigint) meta_diameter from gd"
    out["symmetrize_cite"] = f"with {_CITE_E} select src, dst from e"
    out["size_arrows_cite"] = f"with {_CITE_E} select count(*) edges, 2 * count(*) arrows from e"

    for name in CLUSTERED:
        w = f"with recursive {CTE[name]}{_HALF}{_bfs(4)}"
        out[f"kw_centres_{name}"] = f"{w} select r centre_rank, vid from lab_c"
        out[f"kw_centres_per_subgraph_{name}"] = f"with {CTE[name]}, picked as (select vid from v qualify row_number() over (partition by sg order by md5('7:0:pick:' || vid), vid) <= 4) select cast(row_number() over (order by md5('7:0:' || vid), vid) - 1 as int) centre_rank, vid from picked qualify centre_rank < 4"
        for unit in ("vertex", "subgraph"):
            out[f"kw_labels_{unit}_{name}"] = f"{w} select vid, dist, centre_rank from lab"
        out[f"kw_cut_{name}"] = f"{w}{_OWNED} select count(*) filter (ps = qs) local_cut, count(*) filter (ps <> qs) remote_cut {_cut()}"
        ends = ", ends as (select p.centre_rank r, p.centre_rank is not distinct from q.centre_rank same from e left join lab p on src = p.vid left join lab q on dst = q.vid union all select q.centre_rank, false from e left join lab p on src = p.vid left join lab q on dst = q.vid where p.centre_rank is distinct from q.centre_rank)"
        out[f"kw_profile_{name}"] = f"{w}{ends} select centre_rank, count(*) vertices, cast(max(dist) as bigint) radius, (select count(*) from ends where r = centre_rank and same) inner_edges, (select count(*) from ends where r = centre_rank and not same) cut_edges from lab group by centre_rank"
        out[f"kw_check_{name}"] = f"{w} select centre_rank, count(*) vertices, 1 pieces from lab group by centre_rank"
    for name in ("nation", "copart"):
        out[f"kw_exchange_{name}"] = f"with {CTE[name]}, c as (select sg, vid, md5('7:0:' || vid) k from v qualify row_number() over (partition by sg order by k, vid) <= 4), got as (select cast(row_number() over (order by k, vid) - 1 as int) centre_rank, vid, count(*) over () received from c qualify centre_rank < 4) select to_sg, received, centre_rank, vid from got, (select distinct sg to_sg from v)"
    for name in ("nation", "copart_strong"):
        out[f"kw_weighted_{name}"] = f"with recursive {CTE[name]}{_HALF}{_bfs(4)}, far(r, vid, d) using key (r, vid) as (select r, vid, cast(0 as bigint) from lab_c union select f.r, h.w, min(f.d + h.weight) from far f join h on h.u = f.vid left join recurring.far old on old.r = f.r and old.vid = h.w where old.vid is null or f.d + h.weight < old.d group by f.r, h.w) select vid, cast(min(d) as bigint) dist, cast(arg_min(r, (d, r)) as int) centre_rank from far group by vid"

    def run_sql(name: str, k: int, percent: int, rounds: int = 3, strict: bool = False) -> str:
        w = f"with recursive {CTE[name]}{_HALF}{_OWNED}" + "".join(_bfs(k, round_=r, name=f"lab{r}") for r in range(rounds))
        cuts = " union all ".join(f"select {r} r, (select count(*) {_cut(f'lab{r}')}) cut" for r in range(rounds))
        return f"{w}, cuts as ({cuts}), lim as (select count(*) * {percent} // 100 tau from e), hit as (select min(r) r from cuts, lim where cut {'<' if strict else '<='} tau) select tau, coalesce(hit.r, (select r from cuts order by cut, r limit 1)) round, coalesce(hit.r + 1, {rounds}) rounds, (select cut from cuts where cuts.r = coalesce(hit.r, (select r from cuts order by cut, r limit 1))) cut, cast(hit.r is not null as int) ok from lim, hit"

    for k, percent in RUN_GRID:
        out[f"kw_run_copart_strong_k{k}_tau{percent}"] = run_sql("copart_strong", k, percent)
    for unit in ("vertex", "subgraph"):
        for name in ("order_cite", "page_colink"):
            out[f"kw_run_{unit}_{name}"] = run_sql(name, 4, 50)
    out["kw_run_never_met_nation"] = run_sql("nation", 4, 0, strict=True)
    out["bsp_votes_nation"] = f"with {CTE['nation']}{_OWNED}, s as (select count(distinct sg) n from v) select 0 superstep, 'draw' phase, n * n active, n msgs_local, n * n - n msgs_remote from s union all select 1, 'exchange', count(*), count(*) filter (ps = qs), count(*) filter (ps <> qs) from o union all select 2, case when exists (select 1 from o where ps <> qs) then 'exchange' else 'done' end, 0, 0, 0"

    for name in FEW:
        w = f"with recursive {CTE[name]}{_MSF}"
        for unit in ("vertex", "subgraph", "single", "filter"):
            out[f"msf_{unit}_{name}"] = f"{w} select src, dst, weight from f"
        out[f"msf_summary_{name}"] = f"{w} select count(*) edges, cast(coalesce(sum(weight), 0) as bigint) weight, (select count(*) from v) - count(*) trees from f"
        out[f"msf_trees_{name}"] = f"with recursive {CTE[name]}{_COMP} select vid, comp root from cc"
        kept = "f1 as (select src, dst, weight from f qualify row_number() over (order by weight desc, src desc, dst desc) > 3)"
        link = _COMP.replace("from e union all", "from f1 union all").replace("weight from e)", "weight from f1)")
        out[f"single_linkage_{name}"] = f"{w}, {kept}{link} select vid, comp as cluster from cc"
    for name in ("copart", "order_cite", "user_coact", "emb_knn", "page_colink", "conv_next"):
        out[f"msf_summary_{name}"] = f"with recursive {CTE[name]}{_COMP} select count(*) - count(distinct comp) edges, count(distinct comp) trees from cc"

    for name in ("nation", "copart_strong", "order_cite"):
        w = f"with recursive {CTE[name]}{_HALF}, d(vid, dist) using key (vid) as (select vid, cast(0 as bigint) from v where vid in ({{}}) union select h.w, min(d.dist) + 1 from d join h on h.u = d.vid left join recurring.d old on old.vid = h.w where old.vid is null group by h.w)"
        out[f"bfs_from_0_{name}"] = out[f"bfs_subgraph_from_0_{name}"] = w.format("0") + " select vid, dist from d"
        out[f"reachable_{name}"] = w.format("0, 1") + " select v.vid, d.vid is not null reached from v left join d on v.vid = d.vid"
        out[f"pagerank_{name}"] = f"{_rank_sql(name)} select vid, score from p5"
        out[f"subgraph_rank_{name}"] = f"{_rank_sql(name)} select sg, cast(sum(score) as bigint) score from p5 join v on p5.vid = v.vid group by sg"
        out[f"coarsen_{name}"] = f"with {CTE[name]}{_OWNED} select least(ps, qs) src, greatest(ps, qs) dst, min(weight) weight from o where ps <> qs group by 1, 2"
    out["betweenness_nation"] = _between_sql("nation", [0, 1, 2], 2)
    out["tri_list_page_colink"] = out["tri_kernel_list_page_colink"] = f"with {CTE['page_colink']}{_TYPED} select a, b, c, tri_type from tt"
    registered = queries()
    return {name: sql for name, sql in out.items() if name in registered}
