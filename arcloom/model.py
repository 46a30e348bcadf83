"""The graph: vertices (id, color) and arcs (src, dst, weight), every edge in both directions."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

#: Bytes up to which a vertex relation is broadcast; rows of id and value take 16.
BROADCAST_BYTES = 32 << 20


@dataclass(frozen=True)
class PropertyGraph:
    vertices: DataFrame
    edges: DataFrame

    @property
    def spark(self) -> SparkSession:
        return self.vertices.sparkSession

    def arcs(self, *columns: str) -> DataFrame:
        """Arcs dealt by src and kept, so that rounds of joins on src move state only."""
        return self.edges.select("src", "dst", *columns).repartition("src").persist()


def small(df: DataFrame, rows: int, row_bytes: int = 16) -> DataFrame:
    """Broadcast a side whose counted size is within bounds; else leave the join to a shuffle."""
    return F.broadcast(df) if rows * row_bytes <= BROADCAST_BYTES else df


def simplify(edges: DataFrame, merge: str = "min") -> DataFrame:
    """Both directions of every edge once: loops go, parallels merge by min, max, avg or capped sum."""
    how = {"min": F.min("weight"), "max": F.max("weight"), "avg": F.avg("weight"), "sum": F.least(F.sum("weight"), F.lit(1.0))}[merge]
    one = edges.where("src <> dst").groupBy(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).agg(how.alias("weight"))
    return both_ways(one, "a", "b")


def both_ways(edges: DataFrame, a: str = "src", b: str = "dst") -> DataFrame:
    """Arcs of edges that are given once; one pass over the input."""
    ends = F.array(F.struct(F.col(a).alias("src"), F.col(b).alias("dst")), F.struct(F.col(b).alias("src"), F.col(a).alias("dst")))
    return edges.select(F.explode(ends).alias("e"), "weight").select("e.src", "e.dst", "weight")


def degrees(g: PropertyGraph) -> DataFrame:
    """(id, degree), isolated vertices included."""
    d = g.edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("degree"))
    return g.vertices.select("id").join(d, "id", "left").select("id", F.coalesce("degree", F.lit(0)).cast("long").alias("degree"))


def validate(g: PropertyGraph) -> DataFrame:
    """(rule, broken): how many rows break each rule of the model."""
    v, e = g.vertices, g.edges
    back = e.select(F.col("src").alias("dst"), F.col("dst").alias("src"), F.col("weight").alias("other"))
    checks = {
        "id is null": v.where("id is null"),
        "id repeats": v.groupBy("id").count().where("count > 1"),
        "color outside 0..1": v.where("color is null or color < 0 or color > 1"),
        "weight outside 0..1": e.where("weight is null or weight < 0 or weight > 1"),
        "loop": e.where("src = dst"),
        "parallel arcs": e.groupBy("src", "dst").count().where("count > 1"),
        "no arc back": e.join(back, ["src", "dst"], "left").where("other is null or other <> weight"),
        "endpoint unknown": e.join(v.select(F.col("id").alias("src")), "src", "left_anti"),
    }
    parts = [df.agg(F.lit(name).alias("rule"), F.count("*").alias("broken")) for name, df in checks.items()]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def repair(g: PropertyGraph) -> PropertyGraph:
    v = g.vertices.where("id is not null").groupBy("id").agg(F.min(F.least(F.greatest(F.coalesce("color", F.lit(0.5)), F.lit(0.0)), F.lit(1.0))).alias("color"))
    e = simplify(g.edges.where("src is not null and dst is not null").withColumn("weight", F.least(F.greatest(F.coalesce("weight", F.lit(1.0)), F.lit(0.0)), F.lit(1.0))))
    ids = v.select("id")
    e = e.join(ids.withColumnRenamed("id", "src"), "src", "left_semi").join(ids.withColumnRenamed("id", "dst"), "dst", "left_semi")
    return PropertyGraph(v, e.select("src", "dst", "weight"))


def numbered(df: DataFrame, order: str, out: str) -> DataFrame:
    """Numbers 0, 1, ... in order, by counts of range partitions and their prefix sums."""
    ranged = df.repartitionByRange(order).sortWithinPartitions(order).withColumn("_part", F.spark_partition_id())
    counts = ranged.groupBy("_part").agg(F.count("*").alias("_n"))
    offset = counts.select("_part", F.coalesce(F.sum("_n").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_offset"))
    own = F.row_number().over(Window.partitionBy("_part").orderBy(order)) - 1
    return ranged.withColumn("_own", own).join(F.broadcast(offset), "_part").withColumn(out, (F.col("_own") + F.col("_offset")).cast("long")).drop("_part", "_own", "_offset")


def densify(g: PropertyGraph) -> tuple[PropertyGraph, DataFrame]:
    """Ids 0..n-1, and the mapping (id, dense)."""
    mapping = numbered(g.vertices.select("id"), "id", "dense")
    v = g.vertices.join(mapping, "id").select(F.col("dense").alias("id"), "color")
    e = g.edges.join(mapping.select(F.col("id").alias("src"), F.col("dense").alias("s")), "src").join(mapping.select(F.col("id").alias("dst"), F.col("dense").alias("d")), "dst")
    return PropertyGraph(v, e.select(F.col("s").alias("src"), F.col("d").alias("dst"), "weight")), mapping


def induced(edges: DataFrame, ids: DataFrame) -> DataFrame:
    """Arcs with both ends in ``ids``."""
    s = edges.join(ids.select(F.col("id").alias("src")), "src", "left_semi")
    return s.join(ids.select(F.col("id").alias("dst")), "dst", "left_semi").select(*edges.columns)
