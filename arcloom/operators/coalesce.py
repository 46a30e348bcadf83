"""Kernel 3: adjacency finding and coalescing under frequent updates.

A coalescence replaces a vertex and its neighbours by one vertex of their mean colour. It is a mapping (id, parent)
joined to both ends of the arcs it touches; untouched arcs pass by. The batched engine contracts at once all start
vertices that rank lowest within two hops: their closed neighbourhoods are disjoint, so the result is the one that
contracting them one after another in rank order gives.
"""

from __future__ import annotations

import uuid
from decimal import Decimal

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from arcloom import rng
from arcloom.model import PropertyGraph, both_ways, numbered
from arcloom.plans.iterate import checkpoint_dir, cut
from arcloom.sources.ingest import GRAPHS, SEED, SQL, stored

MERGES = {"min": F.min, "max": F.max, "avg": F.avg}


def adjacent(g: PropertyGraph, ids: DataFrame) -> DataFrame:
    """Arcs that leave the given vertices."""
    return g.edges.join(ids.select(F.col("id").alias("src")), "src", "left_semi")


def contract(g: PropertyGraph, mapping: DataFrame, merge: str = "min", log: list | None = None) -> PropertyGraph:
    """Replace members by their parents: arcs redirected, inner ones dropped, parallels merged, colours averaged.

    Parents are new ids. ``log`` gets what went and what came, by which ``restore`` undoes the contraction.
    """
    members = g.vertices.join(mapping, "id")
    new = members.groupBy(F.col("parent").alias("id")).agg(F.avg("color").alias("color"))
    v = g.vertices.join(mapping, "id", "left_anti").select("id", "color").unionByName(new)
    s, d = mapping.select(F.col("id").alias("src"), F.col("parent").alias("ps")), mapping.select(F.col("id").alias("dst"), F.col("parent").alias("pd"))
    e = g.edges.join(s, "src", "left").join(d, "dst", "left")
    still = e.where("ps is null and pd is null").select("src", "dst", "weight")
    touched = e.where("ps is not null or pd is not null")
    moved = touched.select(F.coalesce("ps", "src").alias("src"), F.coalesce("pd", "dst").alias("dst"), "weight").where("src <> dst").groupBy("src", "dst").agg(MERGES[merge]("weight").alias("weight"))
    if log is not None:
        log.append({"lost_vertices": cut(members.select(*g.vertices.columns)), "new_vertices": cut(mapping.select(F.col("parent").alias("id")).distinct()), "lost_edges": cut(touched.select("src", "dst", "weight"))})
    return PropertyGraph(v, still.unionByName(moved))


def _next_id(g: PropertyGraph) -> int:
    return (g.vertices.agg(F.max("id")).first()[0] or 0) + 1


def neighbourhood(g: PropertyGraph, start: DataFrame) -> DataFrame:
    """(id, start): each start (id) and its neighbours."""
    near = g.edges.join(start.select(F.col("id").alias("src")), "src", "left_semi").select(F.col("dst").alias("id"), F.col("src").alias("start"))
    return start.select("id", F.col("id").alias("start")).unionByName(near)


def pick(g: PropertyGraph, purpose: str, seed: int = SEED) -> DataFrame:
    """The vertex whose hash is least: a draw from the present vertices."""
    return g.vertices.select("id", rng.bits(seed, purpose, "id").alias("r")).orderBy("r", "id").limit(1).select("id")


def coalesce_once(g: PropertyGraph, start: DataFrame, merge: str = "min", log: list | None = None) -> tuple[PropertyGraph, DataFrame]:
    mapping = cut(neighbourhood(g, start).select("id", F.lit(_next_id(g)).cast("long").alias("parent")))
    return contract(g, mapping, merge, log), mapping


def coalesce(g: PropertyGraph, gamma: float | None = None, count: int | None = None, engine: str = "batched", merge: str = "min", seed: int = SEED, log: list | None = None) -> tuple[PropertyGraph, DataFrame, list[dict]]:
    """floor(gamma * n) coalescences (or ``count``): graph, mapping (id, parent) of the whole run, and the trace.

    Rounds go on until all are done or a single vertex is left.
    """
    n = g.vertices.count()
    left = count if count is not None else int(Decimal(str(gamma)) * n)  # 0.01 of 2900 is 29; as doubles it is under 29
    total, trace = None, []
    r = 0
    while left > 0 and n > 1:
        if engine == "sequential":
            g, mapping = coalesce_once(g, pick(g, f"start{r}", seed), merge, log)
            done = 1
        else:
            starts = batch_starts(g, f"start{r}", left, seed)
            first = _next_id(g)
            named = cut(numbered(starts, "id", "k").select("id", (F.col("k") + first).alias("parent")))
            done = named.count()
            mapping = cut(neighbourhood(g, named.select("id")).join(named.select(F.col("id").alias("start"), "parent"), "start").select("id", "parent"))
            g = contract(g, mapping, merge, log)
        g = PropertyGraph(cut(g.vertices), cut(g.edges))
        total = mapping if total is None else cut(total.join(mapping.select(F.col("id").alias("parent"), F.col("parent").alias("p")), "parent", "left").select("id", F.coalesce("p", "parent").alias("parent")).unionByName(mapping.join(total.select(F.col("parent").alias("id")).distinct(), "id", "left_anti")))
        n = g.vertices.count()
        left -= done
        r += 1
        trace.append({"round": r, "coalescences": done, "vertices": n})
    return g, total if total is not None else g.spark.createDataFrame([], "id long, parent long"), trace


def batch_starts(g: PropertyGraph, purpose: str, most: int, seed: int = SEED) -> DataFrame:
    """Vertices that rank lowest within two hops, the lowest ranks first where there are more than ``most``."""
    key = F.struct("r", "id")
    ranked = cut(g.vertices.select("id", rng.bits(seed, purpose, "id").alias("r")))
    e = g.edges.select("src", "dst")

    def spread(low: DataFrame) -> DataFrame:
        near = e.join(low.select(F.col("id").alias("dst"), "k"), "dst").groupBy(F.col("src").alias("id")).agg(F.min("k").alias("m"))
        return low.join(near, "id", "left").select("id", F.least("k", F.coalesce("m", "k")).alias("k"))

    two = spread(spread(ranked.select("id", key.alias("k"))))
    starts = cut(two.where(F.col("k.id") == F.col("id")).select("id", F.col("k.r").alias("r")))
    if starts.count() <= most:
        return starts.select("id")
    return numbered(starts.withColumn("by", F.concat(F.lpad(F.col("r").cast("string"), 20, "0"), F.lpad(F.col("id").cast("string"), 20, "0"))), "by", "k").where(F.col("k") < most).select("id")


def hierarchy(g: PropertyGraph, gammas: list[float], merge: str = "min") -> tuple[list[PropertyGraph], DataFrame]:
    """Graphs of every level and the vertex map (level, id, parent); vertices that stay map to themselves."""
    levels, maps = [g], None
    for level, gamma in enumerate(gammas, 1):
        coarse, mapping, _ = coalesce(levels[-1], gamma, merge=merge)
        whole = levels[-1].vertices.select("id").join(mapping, "id", "left").select(F.lit(level).alias("level"), "id", F.coalesce("parent", "id").alias("parent"))
        maps = whole if maps is None else maps.unionByName(whole)
        levels.append(coarse)
    return levels, maps


def edge_map(fine: PropertyGraph, mapping: DataFrame) -> DataFrame:
    """(src, dst, to_src, to_dst) of a level's arcs; inner arcs map to loops."""
    m = mapping.select("id", "parent")
    e = fine.edges.select("src", "dst").join(m.select(F.col("id").alias("src"), F.col("parent").alias("to_src")), "src", "left").join(m.select(F.col("id").alias("dst"), F.col("parent").alias("to_dst")), "dst", "left")
    return e.select("src", "dst", F.coalesce("to_src", "src").alias("to_src"), F.coalesce("to_dst", "dst").alias("to_dst"))


def restore(after: PropertyGraph, log: list[dict[str, DataFrame]]) -> PropertyGraph:
    """Undo the contractions of a log, the last one first: new vertices go with their arcs, what was lost comes back."""
    for entry in reversed(log):
        new = entry["new_vertices"]
        v = after.vertices.join(new, "id", "left_anti").unionByName(entry["lost_vertices"])
        e = after.edges.select("src", "dst", "weight")
        for end in ("src", "dst"):
            e = e.join(new.withColumnRenamed("id", end), end, "left_anti").select("src", "dst", "weight")
        after = PropertyGraph(v, e.unionByName(entry["lost_edges"]))
    return after


def snapshot(g: PropertyGraph, path: str | None = None) -> str:
    """Save the whole graph; by default to the shared folder."""
    path = path or f"{checkpoint_dir(g.spark)}/snapshot-{uuid.uuid4().hex}"
    g.vertices.write.mode("overwrite").parquet(f"{path}/vertices")
    g.edges.write.mode("overwrite").parquet(f"{path}/edges")
    return path


def reload(spark: SparkSession, path: str) -> PropertyGraph:
    return PropertyGraph(spark.read.parquet(f"{path}/vertices"), spark.read.parquet(f"{path}/edges"))


def apply_updates(g: PropertyGraph, updates: DataFrame) -> PropertyGraph:
    """Updates (op, src, dst, weight[, to]), for both directions of an edge.

    ``add`` puts an edge or sets its weight, ``remove`` takes it out, ``redirect`` moves the edge src-dst with its weight
    to src-to; a loop goes, and of parallels the least weight stays. New ends become vertices only if they are known.
    """
    e, end = g.edges.select("src", "dst", "weight"), updates.where("op in ('add', 'remove')")
    moved = None
    if "to" in updates.columns:
        go = updates.where("op = 'redirect'").select(F.col("src").alias("s"), F.col("dst").alias("d"), "to")
        go = cut(go.join(e, (F.col("s") == F.col("src")) & (F.col("d") == F.col("dst"))).select("s", "d", "to", "weight"))
        end = end.select("op", "src", "dst", "weight").unionByName(go.select(F.lit("remove").alias("op"), F.col("s").alias("src"), F.col("d").alias("dst"), "weight"))
        moved = both_ways(go.where("s <> to").select(F.col("s").alias("src"), F.col("to").alias("dst"), "weight"))
    u = end.select("op", F.explode(F.array(F.struct("src", "dst", "weight"), F.struct(F.col("dst").alias("src"), F.col("src").alias("dst"), "weight"))).alias("e")).select("op", "e.*")
    kept = e.join(u.select("src", "dst").distinct(), ["src", "dst"], "left_anti").select("src", "dst", "weight")
    out = kept.unionByName(u.where("op = 'add'").groupBy("src", "dst").agg(F.min("weight").alias("weight")))
    if moved is not None:
        out = out.unionByName(moved).groupBy("src", "dst").agg(F.min("weight").alias("weight"))
    return PropertyGraph(g.vertices, out)


def summary(before: PropertyGraph, after: PropertyGraph) -> DataFrame:
    """Sizes and colour range after, and what share of vertices and arcs is left."""
    n, m = before.vertices.count(), before.edges.count()
    v = after.vertices.agg(F.count("*").alias("vertices"), F.min("color").alias("low"), F.max("color").alias("high"))
    return v.crossJoin(after.edges.agg(F.count("*").alias("arcs"), F.sum("weight").alias("weight"))).select("vertices", "arcs", "low", "high", "weight", (F.col("vertices") / n).alias("vertices_left"), (F.col("arcs") / m).alias("arcs_left"))


def ranked_wedges(g: PropertyGraph) -> DataFrame:
    """(top, mid, low): two-arc paths whose first end outranks, by (degree, id), both others.

    A hub in the middle needs an end that outranks it, so its neighbours are not paired with each other.
    """
    d = g.edges.groupBy("src").agg(F.count("*").alias("n"))
    rank = lambda end: d.select(F.col("src").alias(end), F.struct("n", F.col("src").alias("i")).alias(f"r_{end}"))
    e = cut(g.edges.select("src", "dst").join(rank("src"), "src").join(rank("dst"), "dst"))
    first = e.where("r_src > r_dst").select(F.col("src").alias("top"), F.col("r_src").alias("r"), F.col("dst").alias("mid"))
    return first.join(e.select(F.col("src").alias("mid"), F.col("dst").alias("low"), "r_dst"), "mid").where("r > r_dst").select("top", "mid", "low")


def pattern(g: PropertyGraph, kind: str) -> DataFrame:
    """Matches of a small pattern: wedge (a, c, b) with centre c and a < b, triangle (x, y, z), or square (a, b, c, d) in turn, a least and b < d.

    Wedges are as many as all pairs at a centre; that is the result. Squares are found without them.
    """
    if kind == "wedge":
        e = g.edges.select("src", "dst")
        return e.select(F.col("dst").alias("a"), F.col("src").alias("c")).join(e.select(F.col("src").alias("c"), F.col("dst").alias("b")), "c").where("a < b").select("a", "c", "b")
    if kind == "triangle":
        from arcloom.operators.metrics import triangles

        return triangles(g)
    if kind != "square":
        raise ValueError(kind)
    w = cut(ranked_wedges(g))
    both = w.withColumnRenamed("mid", "x").join(w.withColumnRenamed("mid", "y"), ["top", "low"]).where("x < y")
    ring = F.array("top", "x", "low", "y")
    at = F.array_position(ring, F.array_min(ring)).cast("int") - 1
    turn = lambda k: F.get(ring, (at + k) % 4)
    return both.select(turn(0).alias("a"), F.least(turn(1), turn(3)).alias("b"), turn(2).alias("c"), F.greatest(turn(1), turn(3)).alias("d"))


def square_count(g: PropertyGraph) -> DataFrame:
    """Every square is counted at its highest rank: k middles of a (top, low) make k(k-1)/2."""
    k = ranked_wedges(g).groupBy("top", "low").agg(F.count("*").alias("k"))
    return k.agg((F.coalesce(F.sum(F.col("k") * (F.col("k") - 1)), F.lit(0)) / 2).cast("long").alias("squares"))


def _facts(g: PropertyGraph) -> DataFrame:
    return g.vertices.agg(F.count("*").alias("vertices"), F.round(F.sum("color"), 6).alias("colors")).crossJoin(g.edges.agg(F.count("*").alias("arcs"), F.round(F.sum("weight"), 6).alias("weight")))


def k3_adjacent(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = GRAPHS["copart"](spark, sf_dir)
    return adjacent(g, g.vertices.where("color > 0.97")).select("src", "dst", F.round("weight", 6).alias("weight"))


def k3_coalesce_once(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = GRAPHS["copart"](spark, sf_dir)
    return _facts(coalesce_once(g, pick(g, "start0"))[0])


def k3_coalesce_3(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _facts(coalesce(GRAPHS["copart"](spark, sf_dir), count=3, engine="sequential")[0])


def k3_batch_round(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = stored(GRAPHS["words"](spark, sf_dir))
    return batch_starts(g, "start0", 1 << 60)


GAMMA = 0.01


def k3_batch_contract(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One batched run of all its coalescences."""
    return _facts(coalesce(stored(GRAPHS["words"](spark, sf_dir)), GAMMA)[0])


def k3_summary(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = stored(GRAPHS["words"](spark, sf_dir))
    s = summary(g, coalesce(g, GAMMA)[0])
    return s.select("vertices", "arcs", *[F.round(c, 6).alias(c) for c in ("low", "high", "weight", "vertices_left", "arcs_left")])


def k3_hierarchy_map(spark: SparkSession, sf_dir: str) -> DataFrame:
    maps = hierarchy(stored(GRAPHS["docline"](spark, sf_dir)), [0.05, 0.05])[1]
    return maps.where("id <> parent").groupBy("level", "parent").agg(F.count("*").alias("members"))


def k3_edge_map(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Arcs of a level that stay, move, and fall inside a new vertex."""
    g = stored(GRAPHS["docline"](spark, sf_dir))
    m = edge_map(g, coalesce(g, 0.05)[1])
    kind = F.when(F.col("to_src") == F.col("to_dst"), "inner").when((F.col("to_src") == F.col("src")) & (F.col("to_dst") == F.col("dst")), "stays").otherwise("moves")
    return m.groupBy(kind.alias("kind")).agg(F.count("*").alias("arcs"))


def k3_restore_equal(spark: SparkSession, sf_dir: str) -> DataFrame:
    g, log = stored(GRAPHS["copart"](spark, sf_dir)), []
    after = coalesce(g, count=2, engine="sequential", log=log)[0]
    return restore(after, log).edges.select("src", "dst", F.round("weight", 6).alias("weight"))


def k3_snapshot(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _facts(reload(spark, snapshot(GRAPHS["custpart"](spark, sf_dir))))


def k3_updates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edges of weight 1 are taken out, the halves of weight a half become a quarter."""
    g = stored(GRAPHS["copart"](spark, sf_dir))
    one = g.edges.where("src < dst and weight = 1.0").select(F.lit("remove").alias("op"), "src", "dst", "weight")
    half = g.edges.where("src < dst and weight = 0.5").select(F.lit("add").alias("op"), "src", "dst", F.lit(0.25).alias("weight"))
    return apply_updates(g, one.unionByName(half)).edges.select("src", "dst", F.round("weight", 6).alias("weight"))


def k3_redirect(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edges of the first supplier to odd ones move to the last supplier."""
    g = stored(GRAPHS["cosupp"](spark, sf_dir))
    low, high = g.vertices.agg(F.min("id"), F.max("id")).first()
    go = g.edges.where((F.col("src") == low) & (F.col("dst") % 2 == 1)).select(F.lit("redirect").alias("op"), F.col("dst").alias("src"), F.col("src").alias("dst"), "weight", F.lit(high).cast("long").alias("to"))
    return apply_updates(g, go).edges.select("src", "dst", F.round("weight", 6).alias("weight"))


QUERIES = {
    "k3_batch_contract": k3_batch_contract,
    "k3_edge_map": k3_edge_map,
    "k3_redirect": k3_redirect,
    "k3_squares": lambda spark, sf_dir: pattern(GRAPHS["docline"](spark, sf_dir), "square"),
    "k3_adjacent": k3_adjacent,
    "k3_coalesce_once": k3_coalesce_once,
    "k3_coalesce_3": k3_coalesce_3,
    "k3_batch_round": k3_batch_round,
    "k3_summary": k3_summary,
    "k3_hierarchy_map": k3_hierarchy_map,
    "k3_restore_equal": k3_restore_equal,
    "k3_snapshot": k3_snapshot,
    "k3_updates": k3_updates,
    "k3_pattern_square": lambda spark, sf_dir: square_count(GRAPHS["userseq"](spark, sf_dir)),
}


def sql_contract(graph: str, steps: int) -> str:
    """Relations v0, e0, then v1, e1, ... after one more coalescence each."""
    out = ["WITH " + SQL[graph], "v0 AS MATERIALIZED (SELECT * FROM v), e0 AS MATERIALIZED (SELECT * FROM e)"]
    for i in range(steps):
        out.append(f"u{i} AS MATERIALIZED (SELECT id FROM v{i} ORDER BY {rng.sql_bits(SEED, f'start{i}', 'id')}, id LIMIT 1), m{i} AS MATERIALIZED (SELECT id FROM u{i} UNION SELECT dst FROM e{i} WHERE src = (SELECT id FROM u{i})), w{i} AS MATERIALIZED (SELECT max(id) + 1 AS id FROM v{i})")
        out.append(f"v{i + 1} AS MATERIALIZED (SELECT id, color FROM v{i} WHERE id NOT IN (SELECT id FROM m{i}) UNION ALL SELECT (SELECT id FROM w{i}), avg(color) FROM v{i} WHERE id IN (SELECT id FROM m{i}))")
        to = f"CASE WHEN {{0}} IN (SELECT id FROM m{i}) THEN (SELECT id FROM w{i}) ELSE {{0}} END"
        out.append(f"e{i + 1} AS MATERIALIZED (SELECT src, dst, min(weight) AS weight FROM (SELECT {to.format('src')} AS src, {to.format('dst')} AS dst, weight FROM e{i}) WHERE src <> dst GROUP BY 1, 2)")
    return ", ".join(out) + f" SELECT (SELECT count(*) FROM v{steps}) AS vertices, (SELECT round(sum(color), 6) FROM v{steps}) AS colors, count(*) AS arcs, round(sum(weight), 6) AS weight FROM e{steps}"


def sql_batch(v: str, e: str, gamma: float, i: int) -> str:
    """Relations m{i} (id, parent) and v{i}, e{i} after a batched run that one round suffices for."""
    return f"""n{i} AS MATERIALIZED (SELECT floor({gamma} * count(*)) AS most, max(id) AS top FROM {v}), a{i} AS MATERIALIZED (SELECT src, dst FROM {e}),
k{i} AS MATERIALIZED (SELECT id, row_number() OVER (ORDER BY {rng.sql_bits(SEED, 'start0', 'id')}, id) AS k FROM {v}),
p{i} AS MATERIALIZED (SELECT id, min(k) AS k FROM (SELECT id, k FROM k{i} UNION ALL SELECT src, k FROM a{i} JOIN k{i} ON id = dst) GROUP BY 1),
q{i} AS MATERIALIZED (SELECT id, min(k) AS k FROM (SELECT id, k FROM p{i} UNION ALL SELECT src, k FROM a{i} JOIN p{i} ON id = dst) GROUP BY 1),
s{i} AS MATERIALIZED (SELECT id, top + row_number() OVER (ORDER BY id) AS parent FROM (SELECT id FROM k{i} JOIN q{i} USING (id, k) ORDER BY k LIMIT (SELECT most FROM n{i})::BIGINT), n{i}),
m{i} AS MATERIALIZED (SELECT id, parent FROM s{i} UNION ALL SELECT dst, parent FROM a{i} JOIN s{i} ON src = id),
v{i} AS MATERIALIZED (SELECT id, color FROM {v} WHERE id NOT IN (SELECT id FROM m{i}) UNION ALL SELECT parent, avg(color) FROM {v} JOIN m{i} USING (id) GROUP BY 1),
e{i} AS MATERIALIZED (SELECT src, dst, min(weight) AS weight FROM (SELECT coalesce(x.parent, src) AS src, coalesce(y.parent, dst) AS dst, weight FROM {e} LEFT JOIN m{i} x ON x.id = src LEFT JOIN m{i} y ON y.id = dst) WHERE src <> dst GROUP BY 1, 2)"""


def sql_facts(v: str, e: str) -> str:
    return f" SELECT (SELECT count(*) FROM {v}) AS vertices, (SELECT round(sum(color), 6) FROM {v}) AS colors, count(*) AS arcs, round(sum(weight), 6) AS weight FROM {e}"


_MAT = lambda graph: "WITH " + SQL[graph].replace("e AS (", "e AS MATERIALIZED (", 1)
_LEVELS = f"{_MAT('docline')}, {sql_batch('v', 'e', 0.05, 1)}, {sql_batch('v1', 'e1', 0.05, 2)}"
_E = " SELECT src, dst, round(weight, 6) AS weight FROM "
ORACLES = {
    "k3_batch_contract": f"{_MAT('words')}, {sql_batch('v', 'e', GAMMA, 1)}" + sql_facts("v1", "e1"),
    "k3_summary": f"{_MAT('words')}, {sql_batch('v', 'e', GAMMA, 1)} SELECT (SELECT count(*) FROM v1) AS vertices, count(*) AS arcs, (SELECT round(min(color), 6) FROM v1) AS low, (SELECT round(max(color), 6) FROM v1) AS high, round(sum(weight), 6) AS weight, round((SELECT count(*) FROM v1) / (SELECT count(*) FROM v), 6) AS vertices_left, round(count(*) / (SELECT count(*) FROM e), 6) AS arcs_left FROM e1",
    "k3_hierarchy_map": _LEVELS + " SELECT 1::INTEGER AS level, parent, count(*) AS members FROM m1 GROUP BY 2 UNION ALL SELECT 2, parent, count(*) FROM m2 GROUP BY 2",
    "k3_edge_map": f"{_MAT('docline')}, {sql_batch('v', 'e', 0.05, 1)}, t AS (SELECT src, dst, coalesce(x.parent, src) AS s, coalesce(y.parent, dst) AS d FROM e LEFT JOIN m1 x ON x.id = src LEFT JOIN m1 y ON y.id = dst) SELECT CASE WHEN s = d THEN 'inner' WHEN s = src AND d = dst THEN 'stays' ELSE 'moves' END AS kind, count(*) AS arcs FROM t GROUP BY 1",
    "k3_redirect": f"WITH {SQL['cosupp']}, z AS (SELECT min(id) AS low, max(id) AS high FROM v), f AS (SELECT src, dst, weight FROM e, z WHERE NOT ((src = low AND dst % 2 = 1) OR (dst = low AND src % 2 = 1)) UNION ALL SELECT dst, high, weight FROM e, z WHERE src = low AND dst % 2 = 1 AND dst <> high UNION ALL SELECT high, dst, weight FROM e, z WHERE src = low AND dst % 2 = 1 AND dst <> high) SELECT src, dst, round(min(weight), 6) AS weight FROM f GROUP BY 1, 2",
    "k3_squares": f"{_MAT('docline')} SELECT DISTINCT p.src AS a, p.dst AS b, q.dst AS c, r.src AS d FROM e p JOIN e q ON q.src = p.dst JOIN e r ON r.dst = q.dst JOIN e s ON s.src = r.src AND s.dst = p.src WHERE p.src < p.dst AND p.src < q.dst AND p.src < r.src AND p.dst < r.src",
    "k3_adjacent": f"WITH {SQL['copart']}" + _E + "e WHERE src IN (SELECT id FROM v WHERE color > 0.97)",
    "k3_coalesce_once": sql_contract("copart", 1),
    "k3_coalesce_3": sql_contract("copart", 3),
    "k3_batch_round": f"WITH {SQL['words']}, me AS MATERIALIZED (SELECT src, dst FROM e), r AS MATERIALIZED (SELECT id, {rng.sql_bits(SEED, 'start0', 'id')} AS r FROM v), k0 AS MATERIALIZED (SELECT id, row_number() OVER (ORDER BY r, id) AS k FROM r), k1 AS MATERIALIZED (SELECT id, min(k) AS k FROM (SELECT id, k FROM k0 UNION ALL SELECT src, k FROM me JOIN k0 ON id = dst) GROUP BY 1), k2 AS (SELECT id, min(k) AS k FROM (SELECT id, k FROM k1 UNION ALL SELECT src, k FROM me JOIN k1 ON id = dst) GROUP BY 1) SELECT k0.id FROM k0 JOIN k2 USING (id) WHERE k0.k = k2.k",
    "k3_restore_equal": f"WITH {SQL['copart']}" + _E + "e",
    "k3_snapshot": f"WITH {SQL['custpart']} SELECT (SELECT count(*) FROM v) AS vertices, (SELECT round(sum(color), 6) FROM v) AS colors, count(*) AS arcs, round(sum(weight), 6) AS weight FROM e",
    "k3_updates": f"WITH {SQL['copart']} SELECT src, dst, round(CASE WHEN weight = 0.5 THEN 0.25 ELSE weight END, 6) AS weight FROM e WHERE weight <> 1.0",
    "k3_pattern_square": f"WITH {SQL['userseq']}, c AS (SELECT x.dst AS a, y.dst AS b, count(*) AS k FROM e x JOIN e y ON x.src = y.src AND x.dst < y.dst GROUP BY 1, 2) SELECT (sum(k * (k - 1)) / 4)::BIGINT AS squares FROM c",
}
