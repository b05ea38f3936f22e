"""Edge lists as files: text with comments, a data source of its own, and made-up graphs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

EDGE = "src bigint, dst bigint, weight bigint"


def text_edges(edges: DataFrame, path: str) -> DataFrame:
    """Write edges as tab-separated text under a comment line, and read them back with a schema."""
    spark = edges.sparkSession
    lines = edges.select(F.concat_ws("\t", "src", "dst", "weight").alias("value"))
    note = spark.createDataFrame([("# src dst weight",)], "value string")
    note.unionByName(lines).write.text(path)
    return spark.read.csv(path, sep="\t", comment="#", schema=EDGE)


def generated(spark: SparkSession, kind: str, n: int, side: int) -> DataFrame:
    """(src, dst), src < dst: a ``ring`` of n, a ``grid`` with rows of ``side``, a ``complete`` graph, or a ``caveman``
    graph of cliques of ``side`` joined in a ring."""
    v = spark.range(n).withColumnRenamed("id", "a")
    if kind == "ring":
        e = v.select("a", F.pmod(F.col("a") + 1, F.lit(n)).alias("b"))
    elif kind == "grid":
        right = v.where(F.pmod("a", F.lit(side)) < side - 1).select("a", (F.col("a") + 1).alias("b"))
        e = right.unionByName(v.where(F.col("a") < n - side).select("a", (F.col("a") + side).alias("b")))
    elif kind == "complete":
        e = v.select("a", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(n - 1).cast("bigint"))).alias("b")).where("a < b")
    elif kind == "caveman":
        first = F.col("a") - F.pmod("a", F.lit(side))
        clique = v.select("a", F.explode(F.sequence(first, first + side - 1)).alias("b")).where("a < b")
        e = clique.unionByName(v.where(F.pmod("a", F.lit(side)) == side - 1).select("a", F.pmod(F.col("a") + 1, F.lit(n)).alias("b")))
    else:
        raise ValueError(kind)
    return e.select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst"))


class _Range(InputPartition):
    def __init__(self, low: int, high: int):
        self.low, self.high = low, high


class _EdgeReader(DataSourceReader):
    def __init__(self, options: dict):
        self.path, self.parts, self.low = options["path"], int(options.get("parts", "4")), int(options.get("from", "0"))

    def _dataset(self):
        import pyarrow.dataset as ds
        from pyarrow import fs

        where, path = fs.FileSystem.from_uri(self.path) if ":" in self.path else (fs.LocalFileSystem(), self.path)
        return ds.dataset(path, filesystem=where, format="parquet")

    def partitions(self):
        import pyarrow.compute as pc

        top = max((pc.max(b.column("src")).as_py() or 0 for b in self._dataset().to_batches(columns=["src"]) if len(b)), default=0) + 1
        cuts = [self.low + max(0, top - self.low) * i // self.parts for i in range(self.parts + 1)]
        return [_Range(a, b) for a, b in zip(cuts, cuts[1:], strict=False)]

    def read(self, partition: _Range):
        import pyarrow.dataset as ds

        inside = (ds.field("src") >= partition.low) & (ds.field("src") < partition.high)
        yield from self._dataset().to_batches(columns=["src", "dst", "weight"], filter=inside)


class EdgeListSource(DataSource):
    """``edgelist``: Parquet edges read in ranges of source vertices; options path, parts, from (least source)."""

    @classmethod
    def name(cls) -> str:
        return "edgelist"

    def schema(self) -> str:
        return EDGE

    def reader(self, schema) -> DataSourceReader:
        return _EdgeReader(dict(self.options))
