"""Readers, writers and a data source for graphs."""

from __future__ import annotations

import uuid

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from arcloom.model import PropertyGraph, numbered
from arcloom.plans.iterate import checkpoint_dir, cut
from arcloom.sources.ingest import GRAPHS, SQL, table

EDGES = "src BIGINT, dst BIGINT, weight DOUBLE"


def fresh(spark: SparkSession, name: str) -> str:
    return f"{checkpoint_dir(spark)}/{name}-{uuid.uuid4().hex}"


def write_edges(edges: DataFrame, path: str, kind: str = "csv", **options) -> None:
    edges.select("src", "dst", "weight").write.mode("overwrite").options(**options).format(kind).save(path)


def read_edges(spark: SparkSession, path: str, kind: str = "csv", corrupt: bool = False) -> DataFrame:
    """Edges with a fixed schema. Rows that do not parse come as nulls, with ``corrupt`` beside their text in ``_bad``."""
    schema = EDGES + (", _bad STRING" if corrupt and kind in ("csv", "json") else "")
    reader = spark.read.schema(schema)
    if kind in ("csv", "json"):
        reader = reader.option("mode", "PERMISSIVE")
        if corrupt:
            reader = reader.option("columnNameOfCorruptRecord", "_bad")
    return reader.format(kind).load(path)


def save_graph(g: PropertyGraph, prefix: str, buckets: int = 16) -> None:
    """Tables <prefix>_vertices and <prefix>_edges; arcs bucketed and sorted by src, so joins on src need no exchange."""
    g.vertices.write.mode("overwrite").format("parquet").saveAsTable(f"{prefix}_vertices")
    g.edges.write.mode("overwrite").format("parquet").bucketBy(buckets, "src").sortBy("src").saveAsTable(f"{prefix}_edges")


def load_graph(spark: SparkSession, prefix: str) -> PropertyGraph:
    return PropertyGraph(spark.table(f"{prefix}_vertices"), spark.table(f"{prefix}_edges"))


class _Part(InputPartition):
    def __init__(self, part: int):
        self.part = part


class _Reader(DataSourceReader):
    def __init__(self, n: int, clique: int, mean_degree: int, parts: int, seed: int):
        self.n, self.clique, self.mean_degree, self.parts, self.seed = n, clique, mean_degree, parts, seed

    def partitions(self):
        return [_Part(i) for i in range(self.parts)]

    def read(self, partition):
        """Attachments of a slice of the vertices, grown on a list of its own that starts with the clique."""
        dice = np.random.default_rng([self.seed, partition.part])
        ends = [x for i in range(self.clique) for j in range(i + 1, self.clique) for x in (i, j)]
        if partition.part == 0:
            yield from ((ends[k], ends[k + 1]) for k in range(0, len(ends), 2))
        for u in range(self.clique + partition.part, self.n, self.parts):
            for _ in range(int(dice.integers(1, 2 * self.mean_degree + 1))):
                v = ends[int(dice.integers(0, len(ends)))]
                ends += [u, v]
                yield u, v


class GraphSource(DataSource):
    """``spark.read.format('graphgen').option('n', ...)``: raw attachments."""

    @classmethod
    def name(cls) -> str:
        return "graphgen"

    def schema(self) -> str:
        return "src bigint, dst bigint"

    def reader(self, schema):
        o = lambda k, d: int(self.options.get(k, d))
        return _Reader(o("n", 1000), o("clique", 5), o("meandegree", 4), o("parts", 4), o("seed", 42))


def io_csv_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = fresh(spark, "csv")
    write_edges(GRAPHS["userseq"](spark, sf_dir).edges, path)
    return read_edges(spark, path).select("src", "dst", F.round("weight", 6).alias("weight"))


def io_json_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = fresh(spark, "json")
    write_edges(GRAPHS["geo"](spark, sf_dir).edges, path, "json")
    return read_edges(spark, path, "json").select("src", "dst", F.round("weight", 6).alias("weight"))


def io_bucketed_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    name = f"arcs_{uuid.uuid4().hex[:12]}"
    save_graph(GRAPHS["custsupp"](spark, sf_dir), name)
    g = load_graph(spark, name)
    return g.edges.join(g.vertices, g.edges["dst"] == g.vertices["id"]).groupBy("src").agg(F.count("*").alias("n"), F.round(F.sum("color"), 6).alias("colors"))


def source_graphgen(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A graph as large as the customers are many: the attachments that each of them made."""
    own = cut(numbered(table(spark, sf_dir, "customer", "c_custkey"), "c_custkey", "src"))
    spark.dataSource.register(GraphSource)
    made = spark.read.format("graphgen").option("n", str(own.count())).load().groupBy("src").agg(F.count("*").alias("n"))
    return own.join(made, "src", "left").select(F.col("c_custkey").alias("src"), F.coalesce("n", F.lit(0)).alias("n"))


QUERIES = {"io_csv_roundtrip": io_csv_roundtrip, "io_json_roundtrip": io_json_roundtrip, "io_bucketed_roundtrip": io_bucketed_roundtrip, "source_graphgen": source_graphgen}
_E = " SELECT src, dst, round(weight, 6) AS weight FROM e"
ORACLES = {
    "io_csv_roundtrip": f"WITH {SQL['userseq']}" + _E,
    "io_json_roundtrip": f"WITH {SQL['geo']}" + _E,
    "io_bucketed_roundtrip": f"WITH {SQL['custsupp']} SELECT src, count(*) AS n, round(sum(color), 6) AS colors FROM e JOIN v ON id = dst GROUP BY 1",
}
