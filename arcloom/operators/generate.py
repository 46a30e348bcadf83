"""Graph generators with power-law degrees, and the generators they are compared with.

Attachment picks an endpoint of an earlier edge at random, which is a pick in proportion to degree. ``pointer`` does so
without shared state: the slot that attachment a picks is a hash; an even slot belongs to a known vertex, an odd one is
what an earlier attachment picked and is followed by hashing again, twice on average. Vertices are numbers 0..n-1, or the
rows of a table numbered by key (``ids``), which the queries take: customers, with orders where edges are drawn one by one.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from arcloom import rng
from arcloom.model import PropertyGraph, both_ways, numbered, simplify
from arcloom.operators.metrics import degree_histogram
from arcloom.plans.iterate import cut
from arcloom.sources.ingest import SEED, table

#: A chain of picks is followed this far; each step goes on with probability a half.
HOPS = 64


def clique(spark: SparkSession, c: int) -> DataFrame:
    """(src, dst) of a complete graph, every edge once."""
    return spark.range(c).select(F.col("id").alias("src"), F.explode(F.sequence(F.col("id") + 1, F.lit(c))).alias("dst")).where(F.col("dst") < c)


def cliques(rows: DataFrame, by: str, node: str) -> DataFrame:
    """(src, dst), src < dst: a complete graph on the nodes of every group. Groups are packed, so pairs are made where they come out."""
    packed = rows.groupBy(by).agg(F.sort_array(F.collect_set(node)).alias("m"))
    each = packed.select(F.posexplode("m").alias("i", "src"), "m")
    return each.select("src", F.explode(F.slice("m", F.col("i") + 2, F.size("m"))).alias("dst"))


def numbers(spark: SparkSession, sf_dir: str, name: str = "customer", key: str = "c_custkey") -> DataFrame:
    """(id): the rows of a table numbered from 0 in order of their key."""
    return cut(numbered(table(spark, sf_dir, name, key), key, "id").select("id"))


def degree_draw(spark: SparkSession, n: int, c: int, mean_degree: int, seed: int = SEED, mode: str = "listing", kind: str = "md5", ids: DataFrame | None = None) -> DataFrame:
    """(id, d): attachments of every vertex past the clique; uniform on 1..2D, or ('target') on 1..D-1 for a mean degree of D."""
    high = 2 * mean_degree if mode == "listing" else max(1, mean_degree - 1)
    past = spark.range(c, max(c, n)) if ids is None else ids.where((F.col("id") >= c) & (F.col("id") < n))
    return past.select("id", rng.randint(seed, "degree", 1, high, "id", kind=kind).alias("d"))


def colored(spark: SparkSession, n: int, seed: int = SEED, kind: str = "md5", ids: DataFrame | None = None) -> DataFrame:
    return (spark.range(n) if ids is None else ids).select("id", rng.uniform(seed, "color", "id", kind=kind).alias("color"))


def weighted(pairs: DataFrame, seed: int = SEED, kind: str = "md5") -> DataFrame:
    return pairs.withColumn("weight", rng.uniform(seed, "weight", F.least("src", "dst"), F.greatest("src", "dst"), kind=kind))


def finish(spark: SparkSession, pairs: DataFrame, n: int, seed: int = SEED, kind: str = "md5", ids: DataFrame | None = None) -> PropertyGraph:
    """Colours, weights, no loops, every edge once and in both directions."""
    once = pairs.where("src <> dst").select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).distinct()
    return PropertyGraph(colored(spark, n, seed, kind, ids), both_ways(weighted(once, seed, kind)))


def attachments(spark: SparkSession, n: int, c: int, mean_degree: int, seed: int, kind: str, mode: str = "listing", block: int = 65536, ids: DataFrame | None = None) -> DataFrame:
    """(a, u): attachment numbers without gaps, by prefix sums over blocks of vertices."""
    d = degree_draw(spark, n, c, mean_degree, seed, mode, kind, ids).withColumn("block", F.floor(F.col("id") / block))
    before = d.groupBy("block").agg(F.sum("d").alias("t")).select("block", F.coalesce(F.sum("t").over(Window.orderBy("block").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    own = F.sum("d").over(Window.partitionBy("block").orderBy("id").rowsBetween(Window.unboundedPreceding, 0)) - F.col("d")
    d = d.withColumn("own", own).join(F.broadcast(before), "block").withColumn("first", F.col("base") + F.col("own"))
    return d.select(F.col("id").alias("u"), F.explode(F.sequence(F.col("first"), F.col("first") + F.col("d") - 1)).alias("a"))


def pointer(spark: SparkSession, n: int, c: int = 5, mean_degree: int = 4, seed: int = SEED, kind: str = "xx", mode: str = "listing", ids: DataFrame | None = None) -> DataFrame:
    """Raw attachments (src, dst), the clique's edges first; loops and repeats are left in."""
    base = c * (c - 1)
    att = attachments(spark, n, c, mean_degree, seed, kind, mode, ids=ids)

    def slot(a: Column) -> Column:
        return F.pmod(rng.bits(seed, "slot", a, kind=kind), base + 2 * a)

    def hop(k: Column, _: Column) -> Column:
        return F.when((k >= base) & ((k - base) % 2 == 1), slot(F.floor((k - base - 1) / 2))).otherwise(k)

    picked = att.withColumn("k", F.aggregate(F.sequence(F.lit(1), F.lit(HOPS)), slot(F.col("a")), hop))
    owner = att.select(F.col("a").alias("owned"), F.col("u").alias("owner"))
    picked = picked.withColumn("owned", F.when(F.col("k") >= base, F.floor((F.col("k") - base) / 2)))
    # Clique endpoints lie pair by pair: (0,1), (0,2), ...; a pair's number gives its row and column.
    pair, side = F.floor(F.col("k") / 2), F.col("k") % 2
    first = F.floor((2 * c - 1 - F.sqrt((2 * c - 1) * (2 * c - 1) - 8 * pair)) / 2)
    second = pair - first * (2 * c - first - 1) / 2 + first + 1
    out = picked.join(owner, "owned", "left").select(F.col("u").alias("src"), F.coalesce("owner", F.when(side == 0, first).otherwise(second)).cast("long").alias("dst"))
    return clique(spark, c).unionByName(out)


def sequential(n: int, c: int = 5, mean_degree: int = 4, seed: int = SEED) -> np.ndarray:
    """The reference: one growing list of endpoints. Rows (u, v)."""
    dice = np.random.default_rng(seed)
    ends = [x for i in range(c) for j in range(i + 1, c) for x in (i, j)]
    for u in range(c, n):
        for _ in range(int(dice.integers(1, 2 * mean_degree + 1))):
            ends += [u, ends[int(dice.integers(0, len(ends)))]]
    return np.array(ends, np.int64).reshape(-1, 2)


def degree_scan(n: int, c: int = 5, mean_degree: int = 4, seed: int = SEED) -> np.ndarray:
    """What the list saves: every pick weighs all vertices by degree."""
    dice = np.random.default_rng(seed)
    pairs = [(i, j) for i in range(c) for j in range(i + 1, c)]
    degree = np.zeros(n)
    degree[:c] = c - 1
    for u in range(c, n):
        for _ in range(int(dice.integers(1, 2 * mean_degree + 1))):
            v = int(np.searchsorted(np.cumsum(degree[: u + 1]), dice.uniform(0, degree[: u + 1].sum()), "right"))
            pairs.append((u, min(v, u)))
            degree[u] += 1
            degree[min(v, u)] += 1
    return np.array(pairs, np.int64)


def partitioned(spark: SparkSession, n: int, c: int = 5, mean_degree: int = 4, parts: int = 8, seed: int = SEED, ids: DataFrame | None = None) -> DataFrame:
    """Every worker grows its slice of the vertices on its own list, which starts with the clique; lists meet at the end."""

    def grow(frame: pd.DataFrame) -> pd.DataFrame:
        dice = np.random.default_rng([seed, int(frame["part"].iloc[0])])
        ends = [x for i in range(c) for j in range(i + 1, c) for x in (i, j)]
        head = len(ends)
        for u in sorted(frame["id"].tolist()):
            for _ in range(int(dice.integers(1, 2 * mean_degree + 1))):
                ends += [u, ends[int(dice.integers(0, len(ends)))]]
        pairs = np.array(ends[head:], np.int64).reshape(-1, 2)
        return pd.DataFrame({"src": pairs[:, 0], "dst": pairs[:, 1]})

    past = spark.range(c, max(c, n)) if ids is None else ids.where(F.col("id") >= c)
    grown = past.select("id", ((F.col("id") - c) % parts).cast("int").alias("part")).groupBy("part").applyInPandas(grow, "src long, dst long")
    return clique(spark, c).unionByName(grown)


def quadrant(spark: SparkSession, scale: int, edge_factor: int = 8, a: float = 0.57, b: float = 0.19, c: float = 0.19, seed: int = SEED, kind: str = "xx", draws: DataFrame | None = None) -> DataFrame:
    """The recursive-quadrant baseline: a draw a level for every edge (``draws``: id), then repeats go. (src, dst)."""
    u = lambda e, level: rng.uniform(seed, "quadrant", e, level, kind=kind)

    def step(acc: Column, level: Column) -> Column:
        x = u(F.col("id"), level)
        return F.struct((acc["s"] * 2 + (x >= a + b).cast("long")).alias("s"), (acc["d"] * 2 + (((x >= a) & (x < a + b)) | (x >= a + b + c)).cast("long")).alias("d"))

    start = F.struct(F.lit(0).cast("long").alias("s"), F.lit(0).cast("long").alias("d"))
    return (spark.range(edge_factor << scale) if draws is None else draws).select(F.aggregate(F.sequence(F.lit(1), F.lit(scale)), start, step).alias("e")).select(F.col("e.s").alias("src"), F.col("e.d").alias("dst")).distinct()


def uniform(spark: SparkSession, n: int, m: int, seed: int = SEED, kind: str = "xx", draws: DataFrame | None = None) -> DataFrame:
    """m pairs without preference, or one for each of ``draws`` (id)."""
    return (spark.range(m) if draws is None else draws).select(rng.randint(seed, "from", 0, n - 1, "id", kind=kind).alias("src"), rng.randint(seed, "to", 0, n - 1, "id", kind=kind).alias("dst"))


C, D = 5, 4


def order_cliques(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A complete graph on the lines of every order."""
    lines = table(spark, sf_dir, "lineitem", "l_orderkey", "l_linenumber")
    return cliques(lines.select("l_orderkey", (F.col("l_orderkey") * 64 + F.col("l_linenumber")).alias("line")), "l_orderkey", "line")


def _grown(spark: SparkSession, sf_dir: str, make):
    ids = numbers(spark, sf_dir)
    return make(ids, ids.count())


def _pointed(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame, int]:
    """Attachments over the customers, these, and their number."""
    ids = numbers(spark, sf_dir)
    n = ids.count()
    return pointer(spark, n, C, D, kind="md5", ids=ids), ids, n


def gen_degree_hist(spark: SparkSession, sf_dir: str) -> DataFrame:
    raw, ids, n = _pointed(spark, sf_dir)
    return degree_histogram(finish(spark, raw, n, ids=ids))


def _edges_of(make):
    """Simple edges, degrees and the largest degree of a generator's graph. ``make`` has (pairs, n) of customers and orders; quadrants have a power of two of vertices."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ids = numbers(spark, sf_dir)
        pairs, n = make(spark, ids, ids.count(), lambda: numbers(spark, sf_dir, "orders", "o_orderkey"))
        h = degree_histogram(finish(spark, cut(pairs), n, kind="xx", ids=ids if n == ids.count() else None))
        return h.agg(F.sum("n").alias("vertices"), (F.sum(F.col("n") * F.col("degree")) / 2).cast("long").alias("edges"), F.max("degree").alias("max_degree"))

    return run


def _quadrants(spark: SparkSession, ids: DataFrame, n: int, draws) -> tuple[DataFrame, int]:
    scale = max(1, (n - 1).bit_length())
    return quadrant(spark, scale, draws=draws()), 1 << scale


def measure_gen_linear(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Attachments and hops a attachment at growing shares of the customers: hops stay level, so work grows as edges do."""
    ids, out = numbers(spark, sf_dir), None
    most = ids.count()
    for n in (most // 16, most // 4, most):
        base = C * (C - 1)
        att = attachments(spark, n, C, D, SEED, "xx", ids=ids)
        slot = lambda a: F.pmod(rng.bits(SEED, "slot", a, kind="xx"), base + 2 * a)
        chain = F.aggregate(F.sequence(F.lit(1), F.lit(HOPS)), F.struct(slot(F.col("a")).alias("k"), F.lit(0).alias("h")), lambda s, _: F.when((s["k"] >= base) & ((s["k"] - base) % 2 == 1), F.struct(slot(F.floor((s["k"] - base - 1) / 2)).alias("k"), (s["h"] + 1).alias("h"))).otherwise(s))
        one = att.select(chain["h"].alias("h")).agg(F.lit(n).alias("n"), F.count("*").alias("attachments"), F.avg("h").alias("hops"), F.max("h").alias("longest"))
        out = one if out is None else out.unionByName(one)
    return out


QUERIES = {
    "gen_clique": order_cliques,
    "gen_colors": lambda spark, sf_dir: _grown(spark, sf_dir, lambda ids, n: colored(spark, n, ids=ids)).select("id", F.round("color", 9).alias("color")),
    "gen_degree_draw": lambda spark, sf_dir: _grown(spark, sf_dir, lambda ids, n: degree_draw(spark, n, C, D, ids=ids)),
    "gen_pointer_edges": lambda spark, sf_dir: _pointed(spark, sf_dir)[0],
    "gen_degree_hist": gen_degree_hist,
    "gen_simplify": lambda spark, sf_dir: simplify(weighted(_pointed(spark, sf_dir)[0])).select("src", "dst", F.round("weight", 9).alias("weight")),
    "gen_partitioned": _edges_of(lambda spark, ids, n, draws: (partitioned(spark, n, ids=ids), n)),
    "gen_quadrant": _edges_of(_quadrants),
    "gen_uniform": _edges_of(lambda spark, ids, n, draws: (uniform(spark, n, 0, draws=draws()), n)),
    "measure_gen_linear": measure_gen_linear,
}

_BASE = C * (C - 1)
#: Customers numbered by key, in SQL.
SQL_IDS = "SELECT row_number() OVER (ORDER BY c_custkey) - 1 AS id FROM customer"
_SLOT = lambda a: f"{rng.sql_bits(SEED, 'slot', a)} % ({_BASE} + 2 * ({a}))"
_PICKS = f"""d AS (SELECT id, {rng.sql_bits(SEED, 'degree', 'id')} % {2 * D} + 1 AS d FROM ({SQL_IDS}) WHERE id >= {C}),
f AS (SELECT id, d, sum(d) OVER (ORDER BY id) - d AS f FROM d), att AS MATERIALIZED (SELECT id AS u, unnest(range(f::BIGINT, (f + d)::BIGINT)) AS a FROM f),
hop(a, k) AS (SELECT a, {_SLOT('a')} FROM att UNION ALL SELECT a, {_SLOT(f'(k - {_BASE} - 1) // 2')} FROM hop WHERE k >= {_BASE} AND (k - {_BASE}) % 2 = 1),
c AS (SELECT i, j, row_number() OVER (ORDER BY i, j) - 1 AS p FROM (SELECT x.range AS i, y.range AS j FROM range({C}) x, range({C}) y WHERE x.range < y.range)),
raw AS (SELECT i AS src, j AS dst FROM c UNION ALL SELECT att.u, coalesce(o.u, CASE WHEN k % 2 = 0 THEN c.i ELSE c.j END) FROM hop JOIN att ON att.a = hop.a LEFT JOIN att o ON k >= {_BASE} AND o.a = (k - {_BASE}) // 2 LEFT JOIN c ON k < {_BASE} AND c.p = k // 2 WHERE k < {_BASE} OR (k - {_BASE}) % 2 = 0)"""
ORACLES = {
    "gen_clique": "WITH l AS (SELECT DISTINCT l_orderkey AS k, l_orderkey * 64 + l_linenumber AS i FROM lineitem) SELECT x.i AS src, y.i AS dst FROM l x JOIN l y ON x.k = y.k AND x.i < y.i",
    "gen_colors": f"SELECT id, round({rng.sql_uniform(SEED, 'color', 'id')}, 9) AS color FROM ({SQL_IDS})",
    "gen_degree_draw": f"SELECT id, {rng.sql_bits(SEED, 'degree', 'id')} % {2 * D} + 1 AS d FROM ({SQL_IDS}) WHERE id >= {C}",
    "gen_pointer_edges": f"WITH RECURSIVE {_PICKS} SELECT src, dst FROM raw",
    "gen_degree_hist": f"WITH RECURSIVE {_PICKS}, s AS (SELECT DISTINCT least(src, dst) AS a, greatest(src, dst) AS b FROM raw WHERE src <> dst), n AS (SELECT id, count(*) AS degree FROM (SELECT a AS id FROM s UNION ALL SELECT b FROM s) GROUP BY 1) SELECT coalesce(degree, 0) AS degree, count(*) AS n FROM ({SQL_IDS}) v LEFT JOIN n USING (id) GROUP BY 1",
    "gen_simplify": f"WITH RECURSIVE {_PICKS}, s AS (SELECT DISTINCT least(src, dst) AS a, greatest(src, dst) AS b FROM raw WHERE src <> dst), w AS (SELECT a, b, round({rng.sql_uniform(SEED, 'weight', 'a', 'b')}, 9) AS weight FROM s) SELECT a AS src, b AS dst, weight FROM w UNION ALL SELECT b, a, weight FROM w",
}
