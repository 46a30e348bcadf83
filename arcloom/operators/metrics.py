"""Kernel 4: graph metrics."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from arcloom import rng
from arcloom.model import PropertyGraph, degrees, numbered, small
from arcloom.operators.search import Dealt, Packed, _once
from arcloom.plans.iterate import cut
from arcloom.sources.ingest import GRAPHS, SEED, SQL, stored, table


def sample_vertices(vertices: DataFrame, m: int, seed: int = SEED, replacement: bool = False) -> DataFrame:
    """(id) of m vertices by the rank of a hash: the same on any partitioning. With replacement: (id, draw)."""
    if replacement:
        n = vertices.count()
        draws = vertices.sparkSession.range(m).select(F.col("id").alias("draw"), rng.randint(seed, "draw", 0, max(0, n - 1), "id").alias("pos"))
        return numbered(vertices.select("id"), "id", "pos").join(draws, "pos").select("id", "draw")
    return vertices.select("id", rng.bits(seed, "sample", "id").alias("r")).orderBy("r", "id").limit(m).select("id")


def _coefficient(closed: Column, degree: Column, degenerate: str) -> Column:
    value = F.when(degree > 1, closed / (degree * (degree - 1)))
    return F.coalesce(value, F.lit(0.0)) if degenerate == "zero" else value


#: Edges that one task takes at most when triangles are counted, if they fall evenly on the parts.
TASK_EDGES = 12_000_000


def _pack(rows: pa.Table) -> pa.Table:
    """Edges of one pair of parts as two arrays, sorted so that the first compresses."""
    a, b = (rows.column(c).to_numpy() for c in "ab")
    order = np.lexsort((b, a))
    return pa.table({"i": rows.column("i").slice(0, 1), "j": rows.column("j").slice(0, 1), "edges": pa.array([np.stack([a[order], b[order]]).astype("<u4").tobytes()], pa.binary())})


def _closed(a: np.ndarray, b: np.ndarray, n: int, cells: int = 1 << 25, most: int = 1 << 18):
    """(x, y, z) of arcs x -> y, y -> z, x -> z, some at a time. Arcs a -> b go upwards and ids are under n.

    The ends of a few x are marked in a table of ``cells`` bytes, and ends of their ends looked up there, ``most`` at a time.
    """
    key = a.astype(np.int64) * n + b
    key.sort()
    a, b = key // n, (key % n).astype(np.int32)
    del key
    out = np.bincount(a, minlength=n)
    start = np.concatenate([[0], np.cumsum(out)])
    heads = np.flatnonzero(out > 1)
    rows = max(1, cells // n)
    mark = np.zeros(rows * n, bool)
    for at in range(0, len(heads), rows):
        xs = heads[at : at + rows]
        arcs = np.repeat(start[xs] - np.cumsum(out[xs]) + out[xs], out[xs]) + np.arange(out[xs].sum())
        line = np.repeat(np.arange(len(xs)) * n, out[xs])
        ends = b[arcs]
        mark[line + ends] = True
        work = np.cumsum(out[ends])
        begin = 0
        while begin < len(arcs):
            end = max(begin + 1, int(np.searchsorted(work, (work[begin - 1] if begin else 0) + most, "right")))
            many, y = out[ends[begin:end]], ends[begin:end]
            last = np.cumsum(many)
            z = b[np.repeat(start[y] - last + many, many) + np.arange(last[-1])]
            hit = np.flatnonzero(mark[np.repeat(line[begin:end], many) + z])
            if len(hit):
                which = np.searchsorted(last, hit, "right")
                yield a[arcs[begin:end]][which], y[which], z[hit]
            begin = end
        mark[line + ends] = False


def _dealt_triangles(g: PropertyGraph, schema: str, work) -> tuple[DataFrame, DataFrame]:
    """``work`` over the triangles of every triple of parts, and the numbers of vertices (id, rank).

    Vertices are numbered by degree, so that arcs from the smaller number leave hubs few, and dealt to p parts by their
    number. The triple of parts that holds the corners of a triangle has all its edges, so p copies of every edge, packed,
    are all that is shuffled; pairs of edges are made and looked up in the task. p grows with the root of the edges.
    """
    by = cut(g.edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("d")).select(F.struct("d", "id").alias("key")))
    ranks = cut(numbered(by, "key", "rank").select("key.id", "rank"))
    n, ends = by.agg(F.count("*"), F.coalesce(F.sum("key.d"), F.lit(0))).first()
    if n > 1 << 32:
        raise ValueError("numbers of vertices are stored in 32 bits")
    p = max(3 if ends > 1 << 16 else 1, int(np.ceil(np.sqrt(3 * ends / TASK_EDGES))))
    deals = max(1, int(ends // (p * p) >> 20))
    one = g.edges.where("src < dst").select("src", "dst")
    for end, rank in (("src", "s"), ("dst", "d")):
        one = one.join(small(ranks.select(F.col("id").alias(end), F.col("rank").alias(rank)), n), end)
    part = lambda c: F.pmod(F.col(c), F.lit(p)).cast("int")
    one = one.select(F.least("s", "d").alias("a"), F.greatest("s", "d").alias("b")).select("a", "b", F.least(part("a"), part("b")).alias("i"), F.greatest(part("a"), part("b")).alias("j"))
    packed = one.groupBy("i", "j", F.pmod(F.xxhash64("a"), F.lit(deals)).alias("deal")).applyInArrow(lambda _, rows: _pack(rows), "i int, j int, edges binary")
    triple = F.array_sort(F.array("i", "j", "k"))
    dealt = packed.withColumn("k", F.explode(F.sequence(F.lit(0), F.lit(p - 1)))).select(triple.alias("triple"), "edges")

    def each(key: tuple, rows: pa.Table) -> pa.Table:
        parts = np.unique(np.array(key[0].as_py()))
        # A number becomes its position among those of these parts, which keeps their order.
        slot = np.zeros(p, np.int64)
        slot[parts] = np.arange(len(parts))
        ends = np.concatenate([np.frombuffer(e.as_buffer(), "<u4").reshape(2, -1) for e in rows.column("edges")], 1).astype(np.int64)
        ends = ends // p * len(parts) + slot[ends % p]

        def found():
            for x, y, z in _closed(*ends, (n // p + 1) * len(parts)):
                if len(parts) == 2:  # those within one part have a triple of their own
                    other = (x % 2 != y % 2) | (y % 2 != z % 2)
                    x, y, z = x[other], y[other], z[other]
                yield x, y, z

        return work(found(), (n // p + 1) * len(parts), lambda at: at // len(parts) * p + parts[at % len(parts)])

    return dealt.groupBy("triple").applyInArrow(each, schema), ranks


def _corners(found, n: int, number) -> pa.Table:
    count = np.zeros(n, np.int64)
    for corners in found:
        for c in corners:
            np.add.at(count, c, 1)
    at = np.flatnonzero(count)
    return pa.table({"rank": number(at), "n": count[at]})


def _listed(found, n: int, number) -> pa.Table:
    rows = [[number(c.astype(np.int64)) for c in corners] for corners in found]
    return pa.table({k: np.concatenate([r[i] for r in rows]) if rows else np.zeros(0, np.int64) for i, k in enumerate("xyz")})


def corners(g: PropertyGraph) -> DataFrame:
    """(id, n): triangles at every vertex that has any."""
    counted, ranks = _dealt_triangles(g, "rank long, n long", _corners)
    return counted.groupBy("rank").agg(F.sum("n").alias("n")).join(ranks, "rank").select("id", "n")


def triangles(g: PropertyGraph) -> DataFrame:
    """(x, y, z), every triangle once, in order of degree."""
    out, ranks = _dealt_triangles(g, "x long, y long, z long", _listed)
    for c in "xyz":
        out = out.join(ranks.withColumnRenamed("rank", c), c).drop(c).withColumnRenamed("id", c)
    return out.select("x", "y", "z")


def clustering(g: PropertyGraph, m: int | None = None, seed: int = SEED, degenerate: str = "null", engine: str = "joins") -> DataFrame:
    """(id, degree, closed, cc): arcs among neighbours over d(d-1), arcs counted in both directions.

    All vertices (``m`` None): triangles are counted at their corners, in triples of parts (``corners``). A
    sample: neighbours of the sampled, two steps, closed by a join. ``engine='arrays'``: packed neighbour sets intersected.
    """
    if engine == "arrays":
        packed = g.edges.groupBy("src").agg(F.collect_list("dst").alias("n"))
        ids = g.vertices.select("id") if m is None else sample_vertices(g.vertices, m, seed)
        own = ids.join(packed, ids["id"] == packed["src"], "left").select("id", F.coalesce("n", F.array().cast("array<long>")).alias("own"))
        each = own.select("id", "own", F.explode_outer("own").alias("v")).join(packed.select(F.col("src").alias("v"), F.col("n").alias("other")), "v", "left")
        out = each.groupBy("id").agg(F.max(F.size("own")).cast("long").alias("degree"), F.sum(F.coalesce(F.size(F.array_intersect("own", "other")), F.lit(0))).cast("long").alias("closed"))
        out = out.select("id", "degree", F.when(F.col("degree") > 0, F.col("closed")).otherwise(0).cast("long").alias("closed"))
    elif m is None:
        corner = corners(g).select("id", (F.col("n") * 2).alias("closed"))
        out = degrees(g).join(corner, "id", "left").select("id", "degree", F.coalesce("closed", F.lit(0)).cast("long").alias("closed"))
    else:
        ids = sample_vertices(g.vertices, m, seed)
        e = g.edges.select("src", "dst")
        near = cut(e.join(ids.withColumnRenamed("id", "src"), "src", "left_semi").select(F.col("src").alias("id"), F.col("dst").alias("v")))
        two = near.join(e.select(F.col("src").alias("v"), F.col("dst").alias("w")), "v")
        closed = two.join(near.select("id", F.col("v").alias("w")), ["id", "w"], "left_semi").groupBy("id").agg(F.count("*").alias("closed"))
        out = ids.join(near.groupBy("id").agg(F.count("*").alias("degree")), "id", "left").join(closed, "id", "left").select("id", F.coalesce("degree", F.lit(0)).cast("long").alias("degree"), F.coalesce("closed", F.lit(0)).cast("long").alias("closed"))
    return out.select("id", "degree", "closed", _coefficient(F.col("closed"), F.col("degree"), degenerate).alias("cc"))


def degree_histogram(g: PropertyGraph) -> DataFrame:
    return degrees(g).groupBy("degree").agg(F.count("*").alias("n"))


def group_arcs(edges: DataFrame, groups: DataFrame) -> DataFrame:
    """Arcs with the groups of both ends (g, h)."""
    return edges.join(groups.select(F.col("id").alias("src"), F.col("group").alias("g")), "src").join(groups.select(F.col("id").alias("dst"), F.col("group").alias("h")), "dst")


def modularity(g: PropertyGraph, groups: DataFrame) -> DataFrame:
    """(group, inner, total, q): inner share of arcs less the share that chance would give; sum q for the whole."""
    arcs = group_arcs(g.edges.select("src", "dst"), groups)
    by = arcs.groupBy(F.col("g").alias("group")).agg(F.sum((F.col("g") == F.col("h")).cast("long")).alias("inner"), F.count("*").alias("total"))
    all_arcs = by.agg(F.sum("total").alias("m"))
    return by.crossJoin(F.broadcast(all_arcs)).select("group", "inner", "total", (F.col("inner") / F.col("m") - (F.col("total") / F.col("m")) ** 2).alias("q"))


def flows(g: PropertyGraph, sources: DataFrame) -> DataFrame | None:
    """(s, src, dst, flow): what goes from source s along an arc if every vertex is sent one unit over its fewest-hop paths; None without arcs.

    Breadth-first with path counts keyed by source, then dependencies are summed back level by level.
    """
    arcs = g.arcs()
    levels = [cut(sources.select(F.col("id").alias("s"), "id", F.lit(1.0).alias("paths")))]
    seen = levels[0].select("s", "id")
    while True:
        step = levels[-1].join(arcs.withColumnRenamed("src", "id"), "id").groupBy("s", F.col("dst").alias("id")).agg(F.sum("paths").alias("paths"))
        new = cut(step.join(seen, ["s", "id"], "left_anti"))
        if new.isEmpty():
            break
        levels.append(new)
        seen = seen.unionByName(new.select("s", "id"))
    total, out = levels[-1].select("s", "id", F.lit(0.0).alias("dep")), None
    for upper, lower in zip(levels[-2::-1], levels[:0:-1], strict=True):
        share = lower.join(total, ["s", "id"]).select("s", F.col("id").alias("dst"), ((F.col("dep") + 1) / F.col("paths")).alias("share"))
        flow = cut(arcs.join(share, "dst").join(upper.select("s", F.col("id").alias("src"), "paths"), ["s", "src"]).select("s", "src", "dst", (F.col("share") * F.col("paths")).alias("flow")))
        out = flow if out is None else out.unionByName(flow)
        back = flow.groupBy("s", F.col("src").alias("id")).agg(F.sum("flow").alias("dep"))
        total = cut(upper.select("s", "id").join(back, ["s", "id"], "left").select("s", "id", F.coalesce("dep", F.lit(0.0)).alias("dep")))
    arcs.unpersist()
    return out


def _dependencies(packed: Packed, cells: int = 1 << 19, arcs_held: int = 1 << 24):
    """Columns (id, score): dependencies summed over the marked sources, by levels forth and back.

    Some sources at a time; what is known of vertex v from the i-th of them is at i n + v. A source that has reached all
    it can sends no more. A level costs what its arcs cost: only slices of more arcs than there are labels go over all labels.
    """
    n, total, size, far = len(packed), np.zeros(len(packed)), packed.reach(), np.iinfo(np.int32).max
    group = max(1, min(cells // max(1, n), arcs_held // max(1, len(packed.to))))
    for at in range(0, len(packed.marked), group):
        s = packed.marked[at : at + group]
        level, tag = np.full(len(s) * n, far, np.int32), np.zeros(len(s) * n, np.int64)
        paths, dep, share = (np.zeros(len(s) * n) for _ in range(3))
        first = np.arange(len(s)) * n + s
        front, left, steps, depth = first, size[s] - 1, [], 0
        level[front], paths[front] = 0, 1.0
        while len(front := front[np.flatnonzero(left[front // n])]):
            depth, v, new, step = depth + 1, front % n, [], []
            for a, b, many, arcs in packed.slices(v, None, max(1 << 17, 2 * len(level))):
                of, many = front[a:b][many > 0], many[many > 0]
                to, sent = packed.to[arcs].astype(np.int64), np.repeat(paths[of], many)
                if len(s) > 1:
                    to += np.repeat(of - of % n, many)
                if len(to) > len(level):
                    got = np.bincount(to, sent, len(level))
                    hit = np.flatnonzero((got > 0) & (level >= depth))
                    paths[hit] += got[hit]
                    fresh, few, used = hit[level[hit] == far], False, len(hit)
                else:
                    down = np.flatnonzero(level[to] >= depth)
                    fresh, few, used = to[down], 4 * len(down) < len(to), len(down)
                    np.add.at(paths, fresh, sent[down])
                    if few:
                        which, to = np.repeat(np.arange(len(of)), many)[down], fresh
                    fresh = _once(fresh[np.flatnonzero(level[fresh] == far)] if new else fresh, tag)
                new.append(fresh)
                level[fresh] = depth
                if used:
                    step.append((of, which if few else np.cumsum(many) - many, to, few))
            front = np.concatenate(new) if new else front[:0]
            left -= np.bincount(front // n, minlength=len(s))
            steps.append((step, front))
        for step, lower in reversed(steps):
            share[lower] = (1 + dep[lower]) / paths[lower]
            for of, by, to, few in step:
                dep[of] = (np.bincount(by, share[to], len(of)) if few else np.add.reduceat(share[to], by)) * paths[of]
            share[lower] = 0.0
        dep[first] = 0.0
        total += dep.reshape(-1, n).sum(0)
    found = np.flatnonzero(total)
    yield packed.ids[found], total[found]


def betweenness(g: PropertyGraph, sources: DataFrame | None = None, batch: int = 512) -> DataFrame:
    """(id, score): dependency of each vertex from all sources, or the given ones (id), along fewest-hop paths.

    Halved, as every pair is seen from both ends when all are sources. Sources are taken ``batch`` at a time, so that the
    state is at most that many rows a vertex. Many sources on a graph that can be mapped are dealt to tasks instead.
    """
    if many := Dealt.of(g, (g.vertices if sources is None else sources).select("id")):
        score = cut(many.run("id long, score double", _dependencies).groupBy("id").agg((F.sum("score") / 2).alias("score")))
        return g.vertices.select("id").join(score, "id", "left").select("id", F.coalesce("score", F.lit(0.0)).alias("score"))
    start = cut((g.vertices if sources is None else sources).select("id"))
    deals, parts = max(1, -(-start.count() // batch)), None
    for i in range(deals):
        f = flows(g, start.where(F.pmod(F.xxhash64("id"), F.lit(deals)) == i))
        if f is not None:
            one = cut(f.where("s <> src").groupBy(F.col("src").alias("id")).agg((F.sum("flow") / 2).alias("score")))
            parts = one if parts is None else parts.unionByName(one)
    if parts is None:
        return g.vertices.select("id", F.lit(0.0).alias("score"))
    score = parts.groupBy("id").agg(F.sum("score").alias("score"))
    return g.vertices.select("id").join(score, "id", "left").select("id", F.coalesce("score", F.lit(0.0)).alias("score"))


def tail(g: PropertyGraph, dmin: int = 4) -> DataFrame:
    """Maximum-likelihood exponent of degrees from dmin on, their number, and the share of arcs at the top 1 %."""
    d = cut(degrees(g).where("degree > 0"))
    at = d.where(F.col("degree") >= dmin).agg(F.count("*").alias("n"), (1 + F.count("*") / F.sum(F.log(F.col("degree") / (dmin - 0.5)))).alias("exponent"))
    edge = d.agg(F.expr("percentile_disc(0.99) within group (order by degree)").alias("p99"))
    top = d.crossJoin(F.broadcast(edge)).agg((F.sum(F.when(F.col("degree") >= F.col("p99"), F.col("degree"))) / F.sum("degree")).alias("top_share"), F.max("degree").alias("max_degree"))
    return at.crossJoin(top)


def approx_error(exact: DataFrame, approx: DataFrame, scale: float, top: int = 10) -> DataFrame:
    """Largest and mean absolute error of scaled scores, rank correlation, and overlap of the top. Ranks are numbered by ranges, not in one task."""
    j = exact.join(approx.select("id", (F.col("score") * scale).alias("guess")), "id")
    for by, rank in (("score", "ra"), ("guess", "rb")):
        j = numbered(cut(j.withColumn("key", F.struct(-F.round(by, 9), F.col("id")))), "key", rank)
    return j.agg(F.max(F.abs(F.col("score") - F.col("guess"))).alias("max_error"), F.avg(F.abs(F.col("score") - F.col("guess"))).alias("mean_error"), F.corr("ra", "rb").alias("rank_correlation"), (F.sum(((F.col("ra") < top) & (F.col("rb") < top)).cast("int")) / top).alias("top_overlap"))


def _cc(name: str, **options):
    return lambda spark, sf_dir: clustering(stored(GRAPHS[name](spark, sf_dir)), **options).select("id", "degree", "closed", F.round("cc", 6).alias("cc"))


def brands(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts grouped by brand: a fixed grouping for densities."""
    return table(spark, sf_dir, "part", "p_partkey", "p_brand").select(F.col("p_partkey").alias("id"), F.col("p_brand").alias("group"))


def k4_triangles(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = stored(GRAPHS["copart"](spark, sf_dir))
    wedges = degrees(g).agg(F.sum(F.col("degree") * (F.col("degree") - 1) / 2).cast("long").alias("wedges"))
    return corners(g).agg((F.coalesce(F.sum("n"), F.lit(0)) / 3).cast("long").alias("triangles")).crossJoin(wedges).select("triangles", "wedges", F.round(3 * F.col("triangles") / F.col("wedges"), 6).alias("transitivity"))


def grid_metric(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean coefficient over samples of growing size, up to all vertices."""
    g, out = stored(GRAPHS["userseq"](spark, sf_dir)), None
    for m in (10, 100, None):
        one = clustering(g, m).agg(F.lit(m or -1).alias("m"), F.count("*").alias("n"), F.round(F.avg("cc"), 6).alias("cc"), F.sum("closed").alias("closed"))
        out = one if out is None else out.unionByName(one)
    return out


def k4_sampling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Approximate samples: rows a kind of vertex under sample and sampleBy, beside the exact draw of as many."""
    v = GRAPHS["partsupp"](spark, sf_dir).vertices.withColumn("kind", (F.col("id") % 8).cast("int"))
    made = {"all": v, "sample": v.sample(0.2, 7), "sampleBy": v.sampleBy("kind", {0: 0.1, 1: 0.5}, 7), "exact": v.join(sample_vertices(v, 50), "id", "left_semi")}
    out = None
    for name, rows in made.items():
        one = rows.groupBy("kind").agg(F.count("*").alias("n")).withColumn("how", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return out


def k4_tail(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tail(GRAPHS["words"](spark, sf_dir)).select("n", F.round("exponent", 6).alias("exponent"), F.round("top_share", 6).alias("top_share"), "max_degree")


def k4_bc_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    return betweenness(stored(GRAPHS["userseq"](spark, sf_dir))).select("id", F.round("score", 6).alias("score"))


def _sampled(spark: SparkSession, sf_dir: str, s: int = 32) -> tuple[PropertyGraph, DataFrame, float]:
    g = stored(GRAPHS["userseq"](spark, sf_dir))
    ids = cut(sample_vertices(g.vertices, s))
    return g, betweenness(g, ids), g.vertices.count() / max(1, ids.count())


def k4_bc_sampled(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, b, scale = _sampled(spark, sf_dir)
    return b.select("id", F.round(F.col("score") * scale, 6).alias("score"))


def measure_bc_error(spark: SparkSession, sf_dir: str) -> DataFrame:
    g, b, scale = _sampled(spark, sf_dir)
    return approx_error(betweenness(g), b, scale)


QUERIES = {
    "k4_cc_sample": _cc("copart", m=100),
    "k4_cc_all": _cc("copart"),
    "k4_cc_arrays": _cc("userseq", engine="arrays"),
    "k4_cc_clique": _cc("cosupp"),
    "k4_cc_bipartite": lambda spark, sf_dir: clustering(GRAPHS["partsupp"](spark, sf_dir)).agg(F.count("*").alias("n"), F.sum("closed").alias("closed")),
    "k4_degree_hist": lambda spark, sf_dir: degree_histogram(GRAPHS["words"](spark, sf_dir)),
    "k4_modularity": lambda spark, sf_dir: modularity(GRAPHS["copart"](spark, sf_dir), brands(spark, sf_dir)).select("group", "inner", "total", F.round("q", 6).alias("q")),
    "k4_triangles": k4_triangles,
    "k4_tail": k4_tail,
    "k4_bc_exact": k4_bc_exact,
    "grid_metric": grid_metric,
    "k4_sampling": k4_sampling,
    "k4_bc_sampled": k4_bc_sampled,
    "measure_bc_error": measure_bc_error,
    "sample_vertices": lambda spark, sf_dir: sample_vertices(GRAPHS["copart"](spark, sf_dir).vertices, 100),
}


def _sql_cc(graph: str, ids: str = "SELECT id FROM v") -> str:
    return f"{_mat(graph)}, s AS ({ids}), d AS (SELECT id, count(dst) AS degree FROM s LEFT JOIN e ON id = src GROUP BY 1), c AS (SELECT a.src AS id, count(*) AS closed FROM e a JOIN s ON s.id = a.src JOIN e b ON b.src = a.dst JOIN e c ON c.src = a.src AND c.dst = b.dst GROUP BY 1) SELECT d.id, degree, coalesce(closed, 0) AS closed, round(CASE WHEN degree > 1 THEN coalesce(closed, 0) / (degree * (degree - 1)) END, 6) AS cc FROM d LEFT JOIN c ON d.id = c.id"


def _mat(graph: str) -> str:
    return "WITH " + SQL[graph].replace("e AS (", "e AS MATERIALIZED (", 1)


def _sql_bc(score: str, sources: str, depth: int = 5) -> str:
    """Scores by path counts of all pairs up to a depth that covers the graph."""
    out = [_mat("userseq"), "a0 AS MATERIALIZED (SELECT id AS s, id AS t, 0 AS d, 1.0::DOUBLE AS n FROM v)"]
    for d in range(1, depth + 1):
        out.append(f"b{d} AS MATERIALIZED (SELECT s, dst AS t, {d} AS d, sum(n) AS n FROM a{d - 1} JOIN e ON src = t WHERE d = {d - 1} GROUP BY 1, 2), a{d} AS MATERIALIZED (SELECT * FROM a{d - 1} UNION ALL SELECT * FROM b{d} WHERE (s, t) NOT IN (SELECT (s, t) FROM a{d - 1}))")
    out.append(f"c AS (SELECT x.t AS id, sum(x.n * y.n / z.n) / 2 AS score FROM a{depth} x JOIN a{depth} y ON y.s = x.t JOIN a{depth} z ON z.s = x.s AND z.t = y.t AND z.d = x.d + y.d WHERE x.s <> x.t AND y.s <> y.t AND x.s IN ({sources}) GROUP BY 1)")
    return ", ".join(out) + f" SELECT id, round({score}, 6) AS score FROM v LEFT JOIN c USING (id)"


_RANK = f"SELECT id FROM v ORDER BY {rng.sql_bits(SEED, 'sample', 'id')}, id LIMIT 100"
_BRAND = "g AS (SELECT p_partkey AS id, p_brand AS \"group\" FROM part), a AS (SELECT x.\"group\" AS g, y.\"group\" AS h FROM e JOIN g x ON x.id = src JOIN g y ON y.id = dst)"
_SOURCES = f"SELECT id FROM (SELECT id FROM v ORDER BY {rng.sql_bits(SEED, 'sample', 'id')}, id LIMIT 32)"
ORACLES = {
    "k4_bc_exact": _sql_bc("coalesce(score, 0.0)", "SELECT id FROM v"),
    "k4_bc_sampled": _sql_bc(f"coalesce(score, 0.0) * ((SELECT count(*) FROM v)::DOUBLE / (SELECT count(*) FROM ({_SOURCES})))", _SOURCES),
    "grid_metric": f"{_mat('userseq')}, r AS MATERIALIZED (SELECT id, row_number() OVER (ORDER BY {rng.sql_bits(SEED, 'sample', 'id')}, id) AS k FROM v), d AS MATERIALIZED (SELECT id, k, count(dst) AS degree FROM r LEFT JOIN e ON id = src GROUP BY 1, 2), c AS MATERIALIZED (SELECT a.src AS id, count(*) AS closed FROM e a JOIN e b ON b.src = a.dst JOIN e c ON c.src = a.src AND c.dst = b.dst GROUP BY 1), f AS (SELECT k, degree, coalesce(closed, 0) AS closed FROM d LEFT JOIN c USING (id)) SELECT m::INTEGER AS m, count(*) AS n, round(avg(CASE WHEN degree > 1 THEN closed / (degree * (degree - 1)) END), 6) AS cc, sum(closed)::BIGINT AS closed FROM f, (SELECT unnest([10, 100, -1]) AS m) WHERE m = -1 OR k <= m GROUP BY 1",
    "k4_cc_sample": _sql_cc("copart", _RANK),
    "k4_cc_all": _sql_cc("copart"),
    "k4_cc_arrays": _sql_cc("userseq"),
    "k4_cc_clique": _sql_cc("cosupp"),
    "k4_cc_bipartite": f"WITH {SQL['partsupp']} SELECT count(*) AS n, 0::BIGINT AS closed FROM v",
    "k4_degree_hist": f"WITH {SQL['words']} SELECT degree, count(*) AS n FROM (SELECT id, count(dst) AS degree FROM v LEFT JOIN e ON id = src GROUP BY 1) GROUP BY 1",
    "k4_modularity": f"WITH {SQL['copart']}, {_BRAND}, b AS (SELECT g AS \"group\", count(*) FILTER (g = h) AS \"inner\", count(*) AS total FROM a GROUP BY 1), m AS (SELECT sum(total) AS m FROM b) SELECT \"group\", \"inner\", total, round(\"inner\" / m - (total / m) * (total / m), 6) AS q FROM b, m",
    "k4_triangles": f"{_mat('copart')}, t AS (SELECT count(*) AS triangles FROM e a JOIN e b ON a.dst = b.src AND a.src < a.dst AND b.src < b.dst JOIN e c ON c.src = a.src AND c.dst = b.dst), w AS (SELECT sum(d * (d - 1) / 2)::BIGINT AS wedges FROM (SELECT count(*) AS d FROM e GROUP BY src)) SELECT triangles, wedges, round(3 * triangles / wedges, 6) AS transitivity FROM t, w",
    "k4_tail": f"WITH {SQL['words']}, d AS (SELECT count(*) AS degree FROM e GROUP BY src), p AS (SELECT quantile_disc(degree, 0.99) AS p99 FROM d) SELECT count(*) FILTER (degree >= 4) AS n, round(1 + count(*) FILTER (degree >= 4) / sum(ln(degree / 3.5)) FILTER (degree >= 4), 6) AS exponent, round((sum(degree) FILTER (degree >= p99) / sum(degree))::DOUBLE, 6) AS top_share, max(degree) AS max_degree FROM d, p",
    "sample_vertices": f"WITH {SQL['copart']} {_RANK}",
}
