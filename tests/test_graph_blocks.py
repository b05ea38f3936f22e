"""Graphs laid over the customers of a given table."""

from partgraph.plans.relational import sc_graph_range


def test_graphs_of_given_customers(spark, sf):
    got = sc_graph_range(spark, sf)
    keys = {r[0] for r in spark.read.parquet(f"{sf}/customer.parquet").select("c_custkey").collect()}
    rows = got.collect()
    assert rows and {v for r in rows for v in (r.src, r.dst)} <= keys and all(r.src // 12 == r.dst // 12 for r in rows)
    assert any("customer.parquet" in f for f in got.inputFiles())
