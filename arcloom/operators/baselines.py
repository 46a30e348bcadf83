"""What the kernels are set against: construction, extreme edges, a multilevel partitioner, edge removal."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from arcloom.model import PropertyGraph, both_ways, simplify
from arcloom.operators.coalesce import hierarchy
from arcloom.operators.grouping import cut_size
from arcloom.operators.metrics import flows, group_arcs, modularity
from arcloom.operators.represent import adjacency
from arcloom.operators.search import components, local
from arcloom.plans.iterate import cut
from arcloom.sources.ingest import GRAPHS, SQL, stored, table


def construct(tuples: DataFrame) -> DataFrame:
    """Packed neighbour lists from raw edge tuples (src, dst, weight)."""
    e = simplify(tuples)
    v = e.select(F.col("src").alias("id")).distinct().withColumn("color", F.lit(0.0))
    return adjacency(PropertyGraph(v, e)).select("id", "nbrs")


def extreme_edges(g: PropertyGraph, which: str = "max") -> DataFrame:
    """All edges that have the largest or smallest weight."""
    best = g.edges.agg((F.max if which == "max" else F.min)("weight").alias("weight"))
    return g.edges.where("src < dst").join(F.broadcast(best), "weight").select("src", "dst", "weight")


def multilevel(g: PropertyGraph, parts: int, levels: int = 2, gamma: float = 0.1, moves: int = 3) -> DataFrame:
    """(id, group): coarsen, cut the coarsest by growing parts from seeds, project back, and move boundary vertices."""
    graphs, maps = hierarchy(PropertyGraph(cut(g.vertices), cut(g.edges)), [gamma] * levels)
    groups = cut(grown(graphs[-1], parts))
    for level in range(levels, 0, -1):
        groups = cut(maps.where(F.col("level") == level).select("id", F.col("parent").alias("p")).join(groups.withColumnRenamed("id", "p"), "p").select("id", "group"))
        fine = graphs[level - 1]
        limit = 1.3 * fine.vertices.count() / parts
        for r in range(moves):
            votes = group_arcs(fine.edges.select("src", "dst"), groups).groupBy(F.col("src").alias("id"), "g", "h").agg(F.count("*").alias("n"))
            best = votes.groupBy("id", "g").agg(F.max_by("h", F.struct("n", -F.col("h"))).alias("to"), F.max("n").alias("n"), F.max(F.when(F.col("h") == F.col("g"), F.col("n"))).alias("own"))
            size = groups.groupBy(F.col("group").alias("to")).agg(F.count("*").alias("size"))
            go = best.join(F.broadcast(size), "to").where((F.col("to") != F.col("g")) & (F.col("n") > F.coalesce("own", F.lit(0))) & (F.col("size") < limit) & (F.pmod(F.xxhash64("id", F.lit(r)), F.lit(2)) == 0)).select("id", "to")
            groups = cut(groups.join(go, "id", "left").select("id", F.coalesce("to", "group").alias("group")))
    return groups


def grown(g: PropertyGraph, parts: int) -> DataFrame:
    """(id, group): greedy parts of equal size, each grown breadth-first from the smallest vertex that is left. One task: for the coarsest graph."""

    def work(adjacent):
        left, room = set(adjacent), -(-len(adjacent) // parts)
        order, part, size, queue = iter(sorted(adjacent)), 0, 0, []
        while left:
            if not queue:
                queue = [next(i for i in order if i in left)]
            v = queue.pop(0)
            if v not in left:
                continue
            left.discard(v)
            yield v, part
            size += 1
            queue += [u for u, _ in adjacent[v] if u in left]
            if size == room and part < parts - 1:
                part, size, queue = part + 1, 0, queue[:1]

    return local(g, "id long, group long", work)


def edge_betweenness(g: PropertyGraph) -> DataFrame:
    """(src, dst, score) along fewest-hop paths, every edge once. For small graphs: a row a source and arc."""
    f = flows(g, g.vertices)
    if f is None:
        return g.spark.createDataFrame([], "src long, dst long, score double")
    return f.groupBy(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).agg((F.sum("flow") / 2).alias("score"))


def edge_removal(g: PropertyGraph, max_removals: int) -> tuple[DataFrame, float]:
    """Take out the most central edge again and again; the components of highest modularity and that modularity."""
    now, best, best_q = g, None, float("-inf")
    for _ in range(max_removals + 1):
        groups = cut(components(now).withColumnRenamed("component", "group"))
        q = modularity(g, groups).agg(F.sum("q")).first()[0] or 0.0
        if q > best_q + 1e-12:
            best, best_q = groups, q
        top = edge_betweenness(now).orderBy(F.desc(F.round("score", 9)), "src", "dst").limit(1)
        gone = both_ways(top.withColumn("weight", F.lit(0.0))).select("src", "dst")
        left = cut(now.edges.join(F.broadcast(gone), ["src", "dst"], "left_anti").select("src", "dst", "weight"))
        if left.isEmpty():
            break
        now = PropertyGraph(g.vertices, left)
    return best, best_q


def base_construct(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = table(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("src"), (F.col("l_suppkey") + 10_000_000).alias("dst"), F.col("l_discount").alias("weight"))
    return construct(t).select("id", F.size("nbrs").cast("long").alias("degree"), F.round(F.aggregate("nbrs", F.lit(0.0), lambda a, n: a + n["weight"]), 6).alias("weight"))


def base_edge_removal(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Components of highest modularity while up to six edges are taken out of the first conversations, which are paths."""
    e = stored(GRAPHS["dialog"](spark, sf_dir)).edges
    low = e.agg(F.min("src")).first()[0]
    e = e.where(f"src < {low + 4096} and dst < {low + 4096}")
    groups, q = edge_removal(PropertyGraph(e.select(F.col("src").alias("id")).distinct().withColumn("color", F.lit(0.0)), cut(e)), 6)
    return groups.groupBy("group").agg(F.count("*").alias("n"), F.lit(round(q, 6)).alias("q"))


QUERIES = {
    "base_edge_removal": base_edge_removal,
    "base_extreme_min": lambda spark, sf_dir: extreme_edges(GRAPHS["partsupp"](spark, sf_dir), "min").select("src", "dst", F.round("weight", 6).alias("weight")),
    "base_construct": base_construct,
    "base_extreme_edges": lambda spark, sf_dir: extreme_edges(GRAPHS["partsupp"](spark, sf_dir)).select("src", "dst", F.round("weight", 6).alias("weight")),
    "base_multilevel_cut": lambda spark, sf_dir: (lambda g: cut_size(g, multilevel(g, 4)))(stored(GRAPHS["docline"](spark, sf_dir))),
}
ORACLES = {
    "base_extreme_min": f"WITH {SQL['partsupp']} SELECT src, dst, round(weight, 6) AS weight FROM e WHERE src < dst AND weight = (SELECT min(weight) FROM e)",
    "base_construct": "WITH t AS (SELECT l_partkey AS a, l_suppkey + 10000000 AS b, min(l_discount) AS w FROM lineitem GROUP BY 1, 2), e AS (SELECT a AS id, w FROM t UNION ALL SELECT b, w FROM t) SELECT id, count(*) AS degree, round(sum(w), 6) AS weight FROM e GROUP BY 1",
    "base_extreme_edges": f"WITH {SQL['partsupp']} SELECT src, dst, round(weight, 6) AS weight FROM e WHERE src < dst AND weight = (SELECT max(weight) FROM e)",
}
