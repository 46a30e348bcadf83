"""Relational operators around the kernels, each on a graph of ``ingest``: one function a query name."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from arcloom.model import PropertyGraph, degrees, induced, small
from arcloom.operators.generate import SQL_IDS, degree_draw, numbers
from arcloom.operators.spectral import pagerank, power
from arcloom.sources.ingest import GRAPHS, SQL, table

R6 = lambda c, a=None: F.round(c, 6).alias(a or c)


def _copart(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    return GRAPHS["copart"](spark, sf_dir)


def filter_color(spark, sf_dir):
    return _copart(spark, sf_dir).vertices.where(F.col("color").between(0.25, 0.5)).select("id", R6("color"))


def filter_weight_range(spark, sf_dir):
    return _copart(spark, sf_dir).edges.where("weight < 1 and weight >= 0.3").select("src", "dst", R6("weight"))


def join_adjacency(spark, sf_dir):
    """Colours summed over neighbours: arcs meet vertex state."""
    g = _copart(spark, sf_dir)
    return g.edges.join(g.vertices.select(F.col("id").alias("dst"), "color"), "dst").groupBy(F.col("src").alias("id")).agg(R6(F.sum("color"), "colors"))


def join_broadcast_frontier(spark, sf_dir):
    g = _copart(spark, sf_dir)
    front = g.vertices.where("color = 1.0").select(F.col("id").alias("src"))
    return g.edges.join(small(front, front.count()), "src").groupBy(F.col("dst").alias("id")).agg(F.count("*").alias("n"))


def join_induced_semi(spark, sf_dir):
    g = _copart(spark, sf_dir)
    return induced(g.edges.select("src", "dst"), g.vertices.where("color > 0.8"))


def join_unvisited_anti(spark, sf_dir):
    g = GRAPHS["docline"](spark, sf_dir)
    near = g.edges.join(g.vertices.where("color = 1.0").select(F.col("id").alias("src")), "src", "left_semi").select(F.col("dst").alias("id")).distinct()
    return g.vertices.select("id").join(near, "id", "left_anti")


def join_degree_outer(spark, sf_dir):
    return degrees(GRAPHS["userseq"](spark, sf_dir))


def graph_diff_full(spark, sf_dir):
    """Arcs of customers to suppliers and to parts, by what only one side has."""
    a = GRAPHS["custsupp"](spark, sf_dir).edges.where("src % 8 = 2").select("src", F.lit(1).alias("a")).groupBy("src").agg(F.count("*").alias("suppliers"))
    b = GRAPHS["custpart"](spark, sf_dir).edges.where("src % 8 = 2").groupBy("src").agg(F.count("*").alias("parts"))
    return a.join(b, "src", "full").where("coalesce(suppliers, 0) <> coalesce(parts, 0)").select("src", F.coalesce("suppliers", F.lit(0)).alias("suppliers"), F.coalesce("parts", F.lit(0)).alias("parts"))


def join_slot_range(spark, sf_dir):
    """Slots to the customer whose range holds them: both sides cut into equal bins, joined on bins, then compared."""
    ids, width = numbers(spark, sf_dir), 64
    n = ids.count()
    w = Window.partitionBy("block").orderBy("id")
    d = degree_draw(spark, n, 5, 4, ids=ids).withColumn("block", F.floor(F.col("id") / 1024))
    base = d.groupBy("block").agg(F.sum("d").alias("t")).select("block", F.coalesce(F.sum("t").over(Window.orderBy("block").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    r = d.withColumn("own", F.sum("d").over(w) - F.col("d")).join(F.broadcast(base), "block").select("id", (F.col("base") + F.col("own")).alias("lo"), (F.col("base") + F.col("own") + F.col("d")).alias("hi"))
    r = r.withColumn("bin", F.explode(F.sequence(F.floor(F.col("lo") / width), F.floor((F.col("hi") - 1) / width))))
    slots = spark.range(0, 4 * n, 7).select(F.col("id").alias("slot"), F.floor(F.col("id") / width).alias("bin"))
    return slots.join(r, "bin").where("slot >= lo and slot < hi").select("slot", F.col("id").alias("owner"))


def join_asof_events(spark, sf_dir):
    """For every click the user's last purchase at or before it: one sorted pass a user, no pairs."""
    ev = table(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type")
    last = F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0))
    return ev.withColumn("purchase", last).where("event_type = 'click'").select("event_id", F.coalesce("purchase", F.lit(-1)).alias("purchase"))


def join_lateral_topk(spark, sf_dir):
    """Each supplier's three heaviest neighbours, ties to smaller ids, by a lateral expansion of packed lists."""
    e = GRAPHS["partsupp"](spark, sf_dir).edges.where("src % 8 = 1")
    packed = e.groupBy("src").agg(F.slice(F.sort_array(F.collect_list(F.struct((-F.col("weight")).alias("w"), "dst"))), 1, 3).alias("top"))
    return packed.select("src", F.explode("top").alias("t")).select("src", "t.dst")


def agg_strength(spark, sf_dir):
    return GRAPHS["custpart"](spark, sf_dir).edges.groupBy(F.col("src").alias("id")).agg(R6(F.sum("weight"), "total"), R6(F.min("weight"), "low"), R6(F.max("weight"), "high"), R6(F.avg("weight"), "mean"), F.count("*").alias("n"), F.min_by("dst", F.struct("weight", "dst")).alias("lightest"))


def agg_color_mean(spark, sf_dir):
    g = GRAPHS["partsupp"](spark, sf_dir)
    return g.vertices.groupBy((F.col("id") % 8).cast("int").alias("kind")).agg(F.count("*").alias("n"), R6(F.avg("color"), "color"), F.sum((F.col("color") > 0.5).cast("long")).alias("dark"))


def agg_distinct_neighbors(spark, sf_dir):
    li = table(spark, sf_dir, "lineitem", "l_suppkey", "l_partkey")
    return li.groupBy("l_suppkey").agg(F.countDistinct("l_partkey").alias("parts"))


def agg_approx_neighbors(spark, sf_dir):
    """Estimated counts and a quantile, with what they miss of the exact ones."""
    li = table(spark, sf_dir, "lineitem", "l_suppkey", "l_partkey", "l_quantity")
    return li.groupBy("l_suppkey").agg(F.approx_count_distinct("l_partkey", 0.02).alias("about"), F.countDistinct("l_partkey").alias("parts"), F.percentile_approx("l_quantity", 0.5).alias("median"))


def _geo_rows(spark, sf_dir):
    c = table(spark, sf_dir, "customer", "c_nationkey", "c_acctbal").select(F.lit("customer").alias("kind"), F.col("c_nationkey").alias("k"), F.col("c_acctbal").alias("b"))
    s = table(spark, sf_dir, "supplier", "s_nationkey", "s_acctbal").select(F.lit("supplier").alias("kind"), F.col("s_nationkey").alias("k"), F.col("s_acctbal").alias("b"))
    n = table(spark, sf_dir, "nation").join(table(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("n_nationkey").alias("k"), F.col("r_name").alias("region"), F.col("n_name").alias("nation"))
    return c.unionByName(s).join(F.broadcast(n), "k")  # nations are 25 at any scale


def _grouped(grouped, *keys):
    return grouped.agg(F.count("*").alias("n"), F.round(F.sum("b"), 2).alias("balance")).select(*[F.coalesce(k, F.lit("all")).alias(k) for k in keys], "n", "balance")


def agg_rollup_geo(spark, sf_dir):
    return _grouped(_geo_rows(spark, sf_dir).rollup("region", "nation"), "region", "nation")


def agg_cube_kind(spark, sf_dir):
    return _grouped(_geo_rows(spark, sf_dir).cube("kind", "region"), "kind", "region")


def agg_grouping_sets(spark, sf_dir):
    return _grouped(_geo_rows(spark, sf_dir).groupingSets([[F.col("kind")], [F.col("region")], []], F.col("kind"), F.col("region")), "kind", "region")


def agg_pivot_degree(spark, sf_dir):
    d = degrees(GRAPHS["partsupp"](spark, sf_dir)).select(F.when(F.col("id") % 8 == 0, "part").otherwise("supplier").alias("kind"), F.floor(F.col("degree") / 10).alias("class"))
    return d.groupBy("class").pivot("kind", ["part", "supplier"]).count().na.fill(0)


def win_rank_score(spark, sf_dir):
    d = degrees(_copart(spark, sf_dir)).join(table(spark, sf_dir, "part", "p_partkey", "p_brand"), F.col("id") == F.col("p_partkey"))
    w = Window.partitionBy("p_brand").orderBy(F.desc("degree"))
    return d.select("id", F.rank().over(w).alias("rank"), F.dense_rank().over(w).alias("dense"), F.row_number().over(Window.partitionBy("p_brand").orderBy(F.desc("degree"), "id")).alias("row"), R6(F.percent_rank().over(w), "pct"))


def win_ntile_degree(spark, sf_dir):
    d = degrees(_copart(spark, sf_dir)).join(table(spark, sf_dir, "part", "p_partkey", "p_brand"), F.col("id") == F.col("p_partkey"))
    return d.select("id", F.ntile(4).over(Window.partitionBy("p_brand").orderBy("degree", "id")).alias("quarter"))


def win_lead_transitions(spark, sf_dir):
    ev = table(spark, sf_dir, "events", "event_id", "ts", "user_id")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return ev.select("event_id", F.coalesce(F.lead("event_id").over(w), F.lit(-1)).alias("next"), F.coalesce(F.lag("event_id").over(w), F.lit(-1)).alias("before"))


def win_csr_offsets(spark, sf_dir):
    """Begin of every part's arcs within its brand, and of the brand."""
    d = degrees(_copart(spark, sf_dir)).join(table(spark, sf_dir, "part", "p_partkey", "p_brand"), F.col("id") == F.col("p_partkey"))
    w = Window.partitionBy("p_brand").orderBy("id").rowsBetween(Window.unboundedPreceding, -1)
    return d.select("id", F.coalesce(F.sum("degree").over(w), F.lit(0)).alias("offset"))


def win_range_value(spark, sf_dir):
    ev = table(spark, sf_dir, "events", "event_id", "ts", "user_id", "value").withColumn("t", F.unix_micros(F.col("ts").cast("timestamp")))
    w = Window.partitionBy("user_id").orderBy("t").rangeBetween(-86_400_000_000, 0)
    return ev.select("event_id", F.count("*").over(w).alias("n"), F.round(F.max("value").over(w), 4).alias("high"))


def topk_eigen(spark, sf_dir):
    """The ten vertices of largest component after ten rounds: the report is a top ten."""
    return power(_copart(spark, sf_dir), 0.0, 10).vector.orderBy(F.desc(F.round("x", 12)), "id").limit(10).select("id", F.round("x", 9).alias("x"))


def topk_per_group(spark, sf_dir):
    d = degrees(_copart(spark, sf_dir)).join(table(spark, sf_dir, "part", "p_partkey", "p_brand"), F.col("id") == F.col("p_partkey"))
    return d.withColumn("r", F.row_number().over(Window.partitionBy("p_brand").orderBy(F.desc("degree"), "id"))).where("r <= 3").select("p_brand", "id", "r")


def _pairs(spark, sf_dir, what):
    """Arcs of the co-purchase graph: the heavy ones, or those between dark vertices."""
    g = GRAPHS["copart"](spark, sf_dir)
    if what == "heavy":
        return g.edges.where("weight >= 0.5").select("src", "dst")
    dark = g.vertices.where("color > 0.8").select("id")
    return g.edges.select("src", "dst").join(dark.withColumnRenamed("id", "src"), "src", "left_semi").join(dark.withColumnRenamed("id", "dst"), "dst", "left_semi").select("src", "dst")


def set_union_edges(spark, sf_dir):
    return _pairs(spark, sf_dir, "heavy").unionByName(_pairs(spark, sf_dir, "dark")).distinct()


def set_intersect_edges(spark, sf_dir):
    return _pairs(spark, sf_dir, "heavy").intersectAll(_pairs(spark, sf_dir, "dark"))


def set_except_edges(spark, sf_dir):
    return _pairs(spark, sf_dir, "dark").exceptAll(_pairs(spark, sf_dir, "heavy"))


NAMES = "filter_color filter_weight_range join_adjacency join_broadcast_frontier join_induced_semi join_unvisited_anti join_degree_outer graph_diff_full join_slot_range join_asof_events join_lateral_topk agg_strength agg_color_mean agg_distinct_neighbors agg_approx_neighbors agg_rollup_geo agg_cube_kind agg_grouping_sets agg_pivot_degree win_rank_score win_ntile_degree win_lead_transitions win_csr_offsets win_range_value topk_eigen topk_per_group set_union_edges set_intersect_edges set_except_edges".split()
QUERIES = {n: globals()[n] for n in NAMES}

from arcloom import rng  # noqa: E402
from arcloom.operators.spectral import sql_power  # noqa: E402
from arcloom.sources.ingest import SEED  # noqa: E402

_C = f"WITH {SQL['copart']}"
_DEG = f"{_C}, d AS (SELECT id, count(dst) AS degree FROM v LEFT JOIN e ON id = src GROUP BY 1), b AS (SELECT id, degree, p_brand FROM d JOIN part ON id = p_partkey)"
_GEO = "WITH g AS (SELECT kind, r_name AS region, n_name AS nation, b FROM (SELECT 'customer' AS kind, c_nationkey AS k, c_acctbal AS b FROM customer UNION ALL SELECT 'supplier', s_nationkey, s_acctbal FROM supplier) JOIN nation ON n_nationkey = k JOIN region ON r_regionkey = n_regionkey)"
_GSEL = lambda keys, by: f"{_GEO} SELECT " + ", ".join(f"coalesce({k}, 'all') AS {k}" for k in keys) + f", count(*) AS n, round(sum(b), 2) AS balance FROM g GROUP BY {by}"
_CS, _CP = "(SELECT DISTINCT o_custkey * 8 + 2 AS src, l_suppkey AS d FROM orders JOIN lineitem ON o_orderkey = l_orderkey)", "(SELECT DISTINCT o_custkey * 8 + 2 AS src, l_partkey AS d FROM orders JOIN lineitem ON o_orderkey = l_orderkey)"
_SETS = f"{_C}, heavy AS (SELECT src, dst FROM e WHERE weight >= 0.5), dark AS (SELECT src, dst FROM e WHERE src IN (SELECT id FROM v WHERE color > 0.8) AND dst IN (SELECT id FROM v WHERE color > 0.8))"
ORACLES = {
    "filter_color": f"{_C} SELECT id, round(color, 6) AS color FROM v WHERE color BETWEEN 0.25 AND 0.5",
    "filter_weight_range": f"{_C} SELECT src, dst, round(weight, 6) AS weight FROM e WHERE weight < 1 AND weight >= 0.3",
    "join_adjacency": f"{_C} SELECT src AS id, round(sum(color), 6) AS colors FROM e JOIN v ON id = dst GROUP BY 1",
    "join_broadcast_frontier": f"{_C} SELECT dst AS id, count(*) AS n FROM e JOIN v ON id = src WHERE color = 1.0 GROUP BY 1",
    "join_induced_semi": f"{_C} SELECT src, dst FROM e WHERE src IN (SELECT id FROM v WHERE color > 0.8) AND dst IN (SELECT id FROM v WHERE color > 0.8)",
    "join_unvisited_anti": f"WITH {SQL['docline']} SELECT id FROM v WHERE id NOT IN (SELECT dst FROM e WHERE src IN (SELECT id FROM v WHERE color = 1.0))",
    "join_degree_outer": f"WITH {SQL['userseq']} SELECT id, count(dst) AS degree FROM v LEFT JOIN e ON id = src GROUP BY 1",
    "graph_diff_full": f"WITH a AS (SELECT src, count(*) AS n FROM {_CS} GROUP BY 1), b AS (SELECT src, count(*) AS n FROM {_CP} GROUP BY 1) SELECT coalesce(a.src, b.src) AS src, coalesce(a.n, 0) AS suppliers, coalesce(b.n, 0) AS parts FROM a FULL JOIN b ON a.src = b.src WHERE coalesce(a.n, 0) <> coalesce(b.n, 0)",
    "join_slot_range": f"WITH d AS (SELECT id, {rng.sql_bits(SEED, 'degree', 'id')} % 8 + 1 AS d FROM ({SQL_IDS}) WHERE id >= 5), r AS (SELECT id, sum(d) OVER (ORDER BY id) - d AS lo, sum(d) OVER (ORDER BY id) AS hi FROM d) SELECT s.range AS slot, id AS owner FROM (SELECT unnest(range(0, 4 * count(*), 7)) AS range FROM customer) s JOIN r ON s.range >= lo AND s.range < hi",
    "join_asof_events": "SELECT event_id, coalesce(last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING), -1) AS purchase FROM events QUALIFY event_type = 'click'",
    "join_lateral_topk": f"WITH {SQL['partsupp']} SELECT src, dst FROM e WHERE src % 8 = 1 QUALIFY row_number() OVER (PARTITION BY src ORDER BY weight DESC, dst) <= 3",
    "agg_strength": f"WITH {SQL['custpart']} SELECT src AS id, round(sum(weight), 6) AS total, round(min(weight), 6) AS low, round(max(weight), 6) AS high, round(avg(weight), 6) AS mean, count(*) AS n, (min(row(weight, dst))).dst AS lightest FROM e GROUP BY 1".replace("(min(row(weight, dst))).dst", "min({'w': weight, 'd': dst}).d"),
    "agg_color_mean": f"WITH {SQL['partsupp']} SELECT (id % 8)::INTEGER AS kind, count(*) AS n, round(avg(color), 6) AS color, sum((color > 0.5)::BIGINT)::BIGINT AS dark FROM v GROUP BY 1",
    "agg_distinct_neighbors": "SELECT l_suppkey, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY 1",
    "agg_rollup_geo": _GSEL(["region", "nation"], "ROLLUP (region, nation)"),
    "agg_cube_kind": _GSEL(["kind", "region"], "CUBE (kind, region)"),
    "agg_grouping_sets": _GSEL(["kind", "region"], "GROUPING SETS ((kind), (region), ())"),
    "agg_pivot_degree": f"WITH {SQL['partsupp']}, d AS (SELECT id, count(dst) AS degree FROM v LEFT JOIN e ON id = src GROUP BY 1) SELECT degree // 10 AS class, count(*) FILTER (id % 8 = 0) AS part, count(*) FILTER (id % 8 = 1) AS supplier FROM d GROUP BY 1",
    "win_rank_score": f"{_DEG} SELECT id, rank() OVER w AS rank, dense_rank() OVER w AS dense, row_number() OVER (PARTITION BY p_brand ORDER BY degree DESC, id) AS row, round(percent_rank() OVER w, 6) AS pct FROM b WINDOW w AS (PARTITION BY p_brand ORDER BY degree DESC)",
    "win_ntile_degree": f"{_DEG} SELECT id, ntile(4) OVER (PARTITION BY p_brand ORDER BY degree, id) AS quarter FROM b",
    "win_lead_transitions": "SELECT event_id, coalesce(lead(event_id) OVER w, -1) AS next, coalesce(lag(event_id) OVER w, -1) AS before FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)",
    "win_csr_offsets": f"{_DEG} SELECT id, coalesce(sum(degree) OVER (PARTITION BY p_brand ORDER BY id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS \"offset\" FROM b",
    "win_range_value": "SELECT event_id, count(*) OVER w AS n, round(max(value) OVER w, 4) AS high FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW)",
    "topk_eigen": sql_power("copart", 10) + " SELECT id, round(x, 9) AS x FROM x10 ORDER BY round(x, 12) DESC, id LIMIT 10",
    "topk_per_group": f"{_DEG} SELECT p_brand, id, row_number() OVER (PARTITION BY p_brand ORDER BY degree DESC, id) AS r FROM b QUALIFY r <= 3",
    "set_union_edges": f"{_SETS} SELECT * FROM heavy UNION SELECT * FROM dark",
    "set_intersect_edges": f"{_SETS} SELECT * FROM heavy INTERSECT ALL SELECT * FROM dark",
    "set_except_edges": f"{_SETS} SELECT * FROM dark EXCEPT ALL SELECT * FROM heavy",
}
