"""Closed forms and invariants on small graphs."""

import itertools
import math
import random
from collections import Counter

import pytest
from pyspark.sql import functions as F

from arcloom.model import PropertyGraph, both_ways, densify, repair, simplify, validate
from arcloom import suite
from arcloom.operators import baselines, coalesce, generate, grouping, metrics, represent, search, spectral
from arcloom.sources import io


def graph(spark, pairs, n, color=lambda i: (i % 10) / 10):
    e = spark.createDataFrame([(a, b, float(w)) for a, b, w in pairs] or [(0, 0, 0.0)], "src long, dst long, weight double").where("src <> dst")
    v = spark.createDataFrame([(i, float(color(i))) for i in range(n)], "id long, color double")
    return PropertyGraph(v, both_ways(e))


@pytest.fixture(scope="module")
def path(spark):
    return graph(spark, [(i, i + 1, 0.5) for i in range(11)], 12)


@pytest.fixture(scope="module")
def clique(spark):
    return graph(spark, [(i, j, 1.0) for i in range(6) for j in range(i + 1, 6)], 6)


@pytest.fixture(scope="module")
def two_parts(spark):
    return graph(spark, [(0, 1, 0.1), (1, 2, 0.1), (0, 2, 1.0), (3, 4, 0.2), (4, 5, 0.2), (3, 5, 0.2)], 7)


def test_engines_agree_on_distances(two_parts):
    want = {0: 0.0, 1: 0.1, 2: 0.2}
    for engine in ("frontier", "full", "bucketed", "ordered"):
        got = {r.id: round(r.dist, 9) for r in search.sssp(two_parts, 0, engine).collect()}
        assert got == want, engine
    assert search.sssp(two_parts, 0, unreached="inf").where("dist = double('inf')").count() == 4
    assert search.sssp(two_parts, 99).count() == 0


def test_path_levels_and_walk(path):
    assert {r.id: r.level for r in search.bfs(path, 0).collect()} == {i: i for i in range(12)}
    assert search.paths(path, 0, [3]).first().path == [0, 1, 2, 3]
    assert [r.position for r in search.dfs(path, 0).orderBy("id").collect()] == list(range(12))


def test_components_and_forest(two_parts):
    assert {r.id: r.component for r in search.components(two_parts).collect()} == {0: 0, 1: 0, 2: 0, 3: 3, 4: 3, 5: 3, 6: 6}
    want = {(0, 1), (1, 2), (3, 4), (3, 5)}
    for engine in ("boruvka", "kruskal", "prim"):
        assert {(r.src, r.dst) for r in search.msf(two_parts, engine).collect()} == want, engine


def test_power_on_clique_and_bipartite(clique, spark):
    s = spectral.power(clique, 1e-9, 20, rayleigh=True)
    assert s.converged and abs(s.rayleigh - 5) < 1e-9 and abs(s.trace[-1]["lambda"] - 5) < 1e-9
    star = graph(spark, [(0, i, 1.0) for i in range(1, 5)], 5)
    assert not spectral.power(star, 1e-6, 12).converged
    assert spectral.power(star, 1e-6, 60, shift=2.0).converged
    assert abs(spectral.pagerank(star, max_iter=5).vector.agg(F.sum("x")).first()[0] - 1) < 1e-9


def test_clustering_closed_forms(clique, path):
    for engine in ("joins", "arrays"):
        assert {r.cc for r in metrics.clustering(clique, engine=engine).collect()} == {1.0}
    assert {r.cc for r in metrics.clustering(path).collect()} == {0.0, None}
    assert {r.closed for r in metrics.clustering(clique, m=3).collect()} == {20}
    assert metrics.triangles(clique).count() == math.comb(6, 3)


def test_betweenness_of_a_path(path):
    got = {r.id: r.score for r in metrics.betweenness(path, batch=5).collect()}
    assert got == {i: float(i * (11 - i)) for i in range(12)}
    ends = {(r.src, r.dst): r.score for r in baselines.edge_betweenness(path).collect()}
    assert ends == {(i, i + 1): float((i + 1) * (11 - i)) for i in range(11)}


def drawn(spark, n, share, seed, weight=lambda dice: 0.5, color=lambda i: 1.0):
    """A graph of random pairs, and its adjacency as plain dictionaries."""
    dice = random.Random(seed)
    pairs = [(a, b, weight(dice)) for a in range(n) for b in range(a + 1, n) if dice.random() < share]
    near = {i: {} for i in range(n)}
    for a, b, w in pairs:
        near[a][b] = near[b][a] = w
    return graph(spark, pairs, n, color), near


def test_searches_against_plain_ones(spark):
    """Distances, hops, predecessors, orders and forests of a random graph with weights of zero."""
    g, near = drawn(spark, 40, 0.08, 3, lambda dice: dice.choice([0.0, 0.25, 0.25, 0.5, 1.0]))
    best = {0: (0.0, 0, None)}
    while True:
        new = dict(best)
        for u, (d, h, _) in best.items():
            for v, w in near[u].items():
                if v and (v not in new or (d + w, h + 1, u) < new[v]):
                    new[v] = (d + w, h + 1, u)
        if new == best:
            break
        best = new
    assert {r.id: (r.dist, r.hops, r.pred) for r in search.path_tree(g, 0).collect()} == best
    for r in search.paths(g, 0, sorted(best)).collect():
        assert r.path[0] == 0 and r.path[-1] == r.target and abs(sum(near[a][b] for a, b in itertools.pairwise(r.path)) - best[r.target][0]) < 1e-12
    seen, stack, order = set(), [0], []
    while stack:
        u = stack.pop()
        if u not in seen:
            seen.add(u)
            order.append(u)
            stack += sorted(near[u], reverse=True)
    assert [r.id for r in search.dfs(g, 0).orderBy("position").collect()] == order
    root = list(range(40))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    forest = set()
    for w, a, b in sorted((w, a, b) for a in near for b, w in near[a].items() if a < b):
        if find(a) != find(b):
            root[find(a)] = find(b)
            forest.add((a, b))
    for engine in ("boruvka", "kruskal", "prim"):
        assert {(r.src, r.dst) for r in search.msf(g, engine).collect()} == forest, engine


def test_rounds_are_unbounded_unless_asked(path):
    whole = search.relax(path, 0, lambda d, w: d + w, 0.0)
    assert whole.converged and whole.state.count() == 12 and whole.work()["rounds"] == 12 and whole.work()["offers"] == 22
    some = search.relax(path, 0, lambda d, w: d + w, 0.0, max_rounds=3)
    assert not some.converged and some.state.count() == 4
    assert {r.id for r in search.sssp(path, 0, target=2).collect()} >= {0, 1, 2}


def test_coalescing(path, clique):
    log: list = []
    n, _ = coalesce.coalesce_once(path, path.spark.createDataFrame([(5,)], "id long"), log=log)
    assert n.vertices.count() == 10 and n.edges.count() == 18
    assert abs(n.vertices.where("id = 12").first().color - 0.5) < 1e-9
    g, mapping, trace = coalesce.coalesce(clique, 0.2)
    assert g.vertices.count() == 1 and mapping.count() == 6 and g.edges.count() == 0
    assert suite.same_graph(coalesce.restore(n, log), path)
    assert coalesce.coalesce(path, 0.0)[0].vertices.count() == 12


def plain_contract(color, near, group):
    """Colours and weights after groups {parent: members} are contracted one after another."""
    color, near = dict(color), {i: dict(r) for i, r in near.items()}
    for parent, members in group.items():
        color[parent] = sum(color[i] for i in members) / len(members)
        row: dict = {}
        for i in members:
            for j, w in near[i].items():
                if j not in members:
                    row[j] = min(w, row.get(j, w))
        for i in members:
            for j in near.pop(i):
                if j in near:
                    near[j].pop(i)
            color.pop(i)
        near[parent] = row
        for j, w in row.items():
            near[j][parent] = w
    return color, near


def test_batched_equals_sequential_in_rank_order(spark):
    """All starts at once give what contracting them one after another gives, and a run is undone by its log."""
    g, near = drawn(spark, 60, 0.04, 5, lambda dice: dice.choice([0.25, 0.5, 1.0]), color=lambda i: (i % 10) / 10)
    starts = sorted(r.id for r in coalesce.batch_starts(g, "start0", 6).collect())
    log: list = []
    after, mapping, trace = coalesce.coalesce(g, count=len(starts), log=log)
    assert len(trace) == 1 and trace[0]["coalescences"] == len(starts) <= 6
    want = plain_contract({i: (i % 10) / 10 for i in range(60)}, near, {60 + k: [s, *near[s]] for k, s in enumerate(starts)})
    assert {r.id: round(r.color, 9) for r in after.vertices.collect()} == {i: round(c, 9) for i, c in want[0].items()}
    assert {(r.src, r.dst): r.weight for r in after.edges.collect()} == {(i, j): w for i, row in want[1].items() for j, w in row.items()}
    assert suite.same_graph(coalesce.restore(after, log), g)
    more: list = []
    small, _, trace = coalesce.coalesce(g, 0.3, log=more)
    assert sum(t["coalescences"] for t in trace) == 18 and len(trace) == len(more) > 1 and suite.same_graph(coalesce.restore(small, more), g)


def test_updates(two_parts):
    rows = [("add", 0, 6, 0.7, None), ("remove", 1, 0, 0.0, None), ("redirect", 3, 4, 0.0, 6), ("redirect", 2, 1, 0.0, 2), ("redirect", 3, 5, 0.0, 4)]
    after = coalesce.apply_updates(two_parts, two_parts.spark.createDataFrame(rows, "op string, src long, dst long, weight double, to long"))
    got = {(r.src, r.dst): r.weight for r in after.edges.where("src < dst").collect()}
    assert got == {(0, 6): 0.7, (0, 2): 1.0, (3, 6): 0.2, (3, 4): 0.2, (4, 5): 0.2}
    assert after.edges.count() == 2 * len(got)


def test_squares_against_plain_pairs(spark):
    g, near = drawn(spark, 25, 0.25, 8)
    want = {(a, b, c, d) for a in near for b in near[a] for d in near[a] if b < d for c in near[b] if c in near[d] and a < min(b, c, d)}
    assert {tuple(r) for r in coalesce.pattern(g, "square").collect()} == want
    assert coalesce.square_count(g).first().squares == len(want)


def test_layouts_give_back_the_arcs(two_parts):
    want = sorted(map(tuple, two_parts.edges.collect()))
    for made in (represent.from_adjacency(represent.adjacency(two_parts)), represent.from_csr(represent.csr(two_parts, 4)), represent.from_linked_list(*represent.linked_list(two_parts))):
        assert sorted(map(tuple, made.select("src", "dst", "weight").collect())) == want
    blocks = represent.csr(two_parts, 4).orderBy("block").collect()
    assert [len(b.offsets) for b in blocks] == [5, 4] and blocks[1].offsets[-1] == blocks[1].offsets[-2]


def test_model_rules(spark):
    e = spark.createDataFrame([(0, 0, 0.5), (0, 1, 0.5), (1, 0, 0.25), (0, 1, 0.75)], "src long, dst long, weight double")
    assert sorted(map(tuple, simplify(e).collect())) == [(0, 1, 0.25), (1, 0, 0.25)]
    g = PropertyGraph(spark.createDataFrame([(0, 0.1), (1, 2.0)], "id long, color double"), e)
    broken = {r.rule: r.broken for r in validate(g).collect()}
    assert broken["loop"] == 1 and broken["color outside 0..1"] == 1
    assert not any(r.broken for r in validate(repair(g)).collect())
    d, mapping = densify(graph(spark, [(3, 5, 1.0)], 6))
    assert mapping.agg(F.max("dense")).first()[0] == 5


def test_groups_partition_and_planted_structure(spark):
    pairs = [(i, j, 1.0) for b in (0, 6) for i in range(b, b + 6) for j in range(i + 1, b + 6)] + [(0, 6, 1.0)]
    g = graph(spark, pairs, 12, color=lambda i: 1.0)
    groups = grouping.split(g, 0.5, 4, "cells")
    assert groups.count() == 12 and groups.select("group").distinct().count() >= 2
    assert grouping.split(g, 1.0, 4).count() == 0
    d = {r.group: r for r in grouping.density(g, g.vertices.select("id", (F.col("id") >= 6).cast("long").alias("group"))).collect()}
    assert d[0].inner == 30 and d[0].outer == 2 and d[0].density == 15.0


def test_splitter_counts_are_exact(spark):
    dice = random.Random(1)
    pairs = {(a, b) for a in range(20) for b in range(a + 1, 20) if dice.random() < 0.3}
    adjacent = {i: [] for i in range(20)}
    for a, b in pairs:
        adjacent[a].append((b, 1.0))
        adjacent[b].append((a, 1.0))
    s = grouping.Splitter(adjacent, "cells")
    s.run(5)
    k = len(s.size)
    want = [[0] * k for _ in range(k)]
    for a, row in adjacent.items():
        for b, _ in row:
            want[s.group[a]][s.group[b]] += 1
    assert s.block == want


def naive_split(near, kind, m):
    """The split loop with the objective computed from scratch at every move."""
    group = dict.fromkeys(near, 0)

    def counts(k):
        size, block = [0] * k, [[0] * k for _ in range(k)]
        for v, g in group.items():
            size[g] += 1
            for u in near[v]:
                block[g][group[u]] += 1
        return size, block

    def value(k):
        size, block = counts(k)
        live = [g for g in range(k) if size[g]]
        if kind == "cells":
            return sum(c * grouping._h(block[a][b] / c) for a in live for b in live if (c := size[a] * (size[a] - 1) if a == b else size[a] * size[b]))
        if len(live) == 1:
            return math.inf
        out = 0.0
        for g in live:
            inner, outer = block[g][g], 2 * (sum(block[g]) - block[g][g])
            p = (min(1.0, inner / outer) if outer else 1.0) if kind == "ratio" else inner / max(1, inner + outer)
            out += grouping._h(p)
        return out

    for _ in range(m):
        k = max(group.values()) + 1
        size, block = counts(k)
        dense = lambda g: block[g][g] / o if (o := 2 * (sum(block[g]) - block[g][g])) else math.inf
        g = min(range(k), key=lambda x: (dense(x), x))
        best, moved = value(k), False
        for v in sorted(x for x, own in group.items() if own == g):
            if sum(own == g for own in group.values()) == 1:
                break
            group[v] = k
            now = value(k + 1)
            if now < best - 1e-9:
                best, moved = now, True
            else:
                group[v] = g
        if not moved:
            break
    return group


@pytest.mark.parametrize("kind", ["ratio", "share", "cells"])
def test_split_against_a_naive_one(spark, kind):
    g, near = drawn(spark, 30, 0.2, 11)
    assert {r.id: r.group for r in grouping.split(g, 0.5, 4, kind).collect()} == naive_split(near, kind, 4)


def test_batched_sweep_finds_planted_groups(spark):
    dice = random.Random(2)
    pairs = [(a, b, 1.0) for a in range(60) for b in range(a + 1, 60) if dice.random() < (0.6 if a % 2 == b % 2 else 0.03)]
    g = graph(spark, pairs, 60, color=lambda i: 1.0)
    groups = grouping.split(g, 0.5, 1, "cells", sweep="batched")
    assert groups.count() == 60
    truth = g.vertices.select("id", (F.col("id") % 2).alias("label"))
    assert grouping.purity(groups, truth).first().purity >= 0.95
    whole = g.vertices.select("id", F.lit(0).cast("long").alias("group"))
    assert grouping.objective(g, groups, "cells").first()[0] < grouping.objective(g, whole, "cells").first()[0]


def test_edge_removal_cuts_the_bridge(spark):
    pairs = [(i, j, 1.0) for b in (0, 4) for i in range(b, b + 4) for j in range(i + 1, b + 4)] + [(0, 4, 1.0)]
    groups, q = baselines.edge_removal(graph(spark, pairs, 8), 2)
    assert {r.id: r.group for r in groups.collect()} == {i: 4 * (i // 4) for i in range(8)} and 0.4 < q < 0.45
    parts = {r.id: r.group for r in baselines.grown(graph(spark, pairs, 8), 2).collect()}
    assert sorted(list(parts.values()).count(p) for p in (0, 1)) == [4, 4]


def test_generators(spark):
    """Attachment grows hubs that uniform pairs do not have, whichever way it is computed."""
    top = lambda pairs: max(Counter(x for p in pairs for x in p).values())
    seq, scan = generate.sequential(2000).tolist(), generate.degree_scan(2000).tolist()
    parted = [tuple(r) for r in generate.partitioned(spark, 2000, parts=3).collect()]
    point = [tuple(r) for r in generate.pointer(spark, 2000, kind="xx").collect()]
    flat = [tuple(r) for r in generate.uniform(spark, 2000, 9000).collect()]
    quad = [tuple(r) for r in generate.quadrant(spark, 11).collect()]
    for pairs in (seq, scan, parted, point):
        assert abs(len(pairs) - 9000) < 700 and all(0 <= x < 2000 for p in pairs for x in p)
        assert top(pairs) > 3 * top(flat)
    assert len(set(quad)) == len(quad) <= 8 << 11 and max(max(p) for p in quad) < 1 << 11 and top(quad) > 3 * top(flat)
    assert len(flat) == 9000
    spark.dataSource.register(io.GraphSource)
    assert sorted(map(tuple, spark.read.format("graphgen").option("n", "2000").option("parts", "3").load().collect())) == sorted(parted)
    g = generate.finish(spark, generate.pointer(spark, 500, kind="xx"), 500, kind="xx")
    assert not any(r.broken for r in validate(g).collect())


def test_no_dense_matrix(clique):
    """The spectral kernel's plan joins arcs with a vector; nothing is crossed or pivoted."""
    text = spectral.multiply(clique.arcs("weight"), clique.vertices.select("id", F.lit(1.0).alias("x")), 6)._jdf.queryExecution().optimizedPlan().toString()
    assert "Cross" not in text and "Pivot" not in text and "Cartesian" not in text


def test_files(spark, two_parts, tmp_path):
    """ORC, partitioned Parquet, and rows that do not parse."""
    want = sorted(map(tuple, two_parts.edges.select("src", "dst", "weight").collect()))
    io.write_edges(two_parts.edges, f"{tmp_path}/orc", "orc")
    assert sorted(map(tuple, io.read_edges(spark, f"{tmp_path}/orc", "orc").collect())) == want
    two_parts.edges.withColumn("part", F.col("src") % 2).write.partitionBy("part").parquet(f"{tmp_path}/parts")
    assert sorted(map(tuple, io.read_edges(spark, f"{tmp_path}/parts", "parquet").where("src is not null").select("src", "dst", "weight").collect())) == want
    (tmp_path / "bad.csv").write_text("1,2,0.5\n3,x,0.5\n")
    got = {r.src: r._bad for r in io.read_edges(spark, str(tmp_path / "bad.csv"), corrupt=True).collect()}
    assert got[1] is None and got[3] == "3,x,0.5"


def test_suite_restores_and_keeps_to_its_budget(spark, clique):
    rows = {(r["kernel"], r["measure"]): r for r in suite.run(clique, rounds=20, count=1, sample=3, alpha=-1.0, budget=1000.0)}
    assert rows["coalesce", "restored"]["value"] == 1.0 and rows["spectral", "eigenvalue"]["value"] == 5.0
    assert rows["metrics", "cc"]["value"] == 1.0 and rows["search", "reached"]["value"] == 6.0 and all(r["within"] for r in rows.values())
    assert not any(r["within"] for r in suite.run(clique, count=1, sample=3, alpha=-1.0, budget=0.0))


def test_sampled_counts_are_near(spark):
    """Approximate distinct counts and samples stay within their error."""
    d = spark.range(20_000).select((F.col("id") % 5).alias("k"), F.col("id").alias("x"))
    assert all(abs(r.n - 4000) < 4000 * 0.15 for r in d.groupBy("k").agg(F.approx_count_distinct("x", 0.05).alias("n")).collect())
    exact = graph(spark, [(i, (i * 7 + 3) % 40, 0.5) for i in range(40)], 40)
    b = metrics.betweenness(exact)
    e = metrics.approx_error(b, b, 1.0).first()
    assert e.max_error == 0.0 and e.rank_correlation == 1.0 and e.top_overlap == 1.0


def test_empty_and_single(spark):
    one = graph(spark, [], 1)
    assert search.sssp(one, 0).count() == 1
    assert search.components(one).first().component == 0
    assert not spectral.power(one, 1e-6, 3).converged
    assert metrics.clustering(one).first().cc is None
