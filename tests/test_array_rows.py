"""Arrays become rows with their places, for each row of a given table."""

from partgraph.plans.relational import sf_array_rows


def test_arrays_of_a_given_table(spark, sf):
    got = sf_array_rows(spark, sf)
    part = spark.read.parquet(f"{sf}/part.parquet").select("p_partkey", "p_size").collect()
    assert sorted(map(tuple, got.collect())) == sorted((r.p_partkey, i, r.p_size * k) for r in part for i, k in enumerate((1, 10, 20, 30), 1))
    assert any("part.parquet" in f for f in got.inputFiles())
