"""Connected components by alternating star contraction; nothing but counters reaches the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import BROADCAST_BYTES, materialise, release

#: Keys with one in so many of all rows are hubs; there are no more hubs than that, which bounds what is broadcast.
HUB_SHARE = 1 << 16


def keyed_join(rows: DataFrame, per_key: DataFrame, keys: list[str], total: int, count: str = "n", least: int = 256) -> DataFrame:
    """``rows`` with the columns of ``per_key``, which has a row a key and the number of its rows in ``count``.

    The rows of a hub do not meet in one task: ``per_key`` is broadcast if it is small, else what belongs to hubs is, and the rest is shuffled.
    """
    if per_key.count() * 8 * len(per_key.columns) <= BROADCAST_BYTES // 2:
        return rows.join(F.broadcast(per_key), keys)
    hub = F.col(count) >= max(least, total // HUB_SHARE)
    hubs = F.broadcast(per_key.where(hub))
    return rows.join(hubs.select(*keys), keys, "left_anti").join(per_key.where(~hub), keys).unionByName(rows.join(hubs, keys))


def _symmetric(edges: DataFrame) -> DataFrame:
    return edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))


def connected_components(edges: DataFrame) -> DataFrame:
    """(node, root) for every node of edges (a, b) of long ids; root is the smallest id of the component.

    A large-star step links every larger neighbour of a node to the node's least neighbour, a small-star step does so
    for the smaller ones. Both are a minimum and a join that spares hubs, so that a hub's neighbours never meet in one
    task. Loops are ignored. No edges: no rows. Rounds go on until nothing changes, about as many as the logarithm of the nodes.
    """
    now = materialise(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "links")
    mark = None
    while True:
        total = 2 * now.count()
        both = _symmetric(now)
        least = both.groupBy("a").agg(F.min("b").alias("m"), F.count("*").alias("n")).select("a", F.least("a", "m").alias("m"), "n").persist()
        large = keyed_join(both, least, ["a"], total).where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct().persist()
        lower = large.groupBy("a").agg(F.min("b").alias("m"), F.count("*").alias("n")).persist()
        star = F.when(F.col("b") > F.col("m"), F.array(F.struct(F.col("b").alias("a"), F.col("m").alias("b")), F.struct("a", F.col("m").alias("b")))).otherwise(F.array(F.struct("a", F.col("m").alias("b"))))
        small = keyed_join(large, lower, ["a"], total).select(F.explode(star).alias("e")).select("e.a", "e.b").where("a <> b").distinct()
        new = materialise(small, "links")
        for df in (lower, large, least):
            df.unpersist()
        release(now)
        now = new
        seen = now.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if tuple(seen) == mark:
            break
        mark = tuple(seen)
    return now.select(F.col("a").alias("node"), F.col("b").alias("root")).unionByName(now.select(F.col("b").alias("node"), F.col("b").alias("root"))).distinct()
