"""One small test a finding of round 3; each fails on the code before it."""

import heapq

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F


def _graph(n, seed=1, some=4):
    """Ids with gaps, arcs both ways (src, dst, weight) with ties, and neighbours by id."""
    dice = np.random.default_rng(seed)
    pairs = sorted({tuple(sorted(p)) for p in dice.integers(0, n, (some * n, 2)).tolist() if p[0] != p[1]})
    rows = [(3 * a, 3 * b, 1.0 / int(w)) for (a, b), w in zip(pairs, dice.integers(1, 6, len(pairs)), strict=True)]
    rows = sorted((r for a, b, w in rows for r in ((a, b, w), (b, a, w))), key=lambda r: (r[0], r[2], r[1]))
    near = {3 * i: [] for i in range(n)}
    for a, b, w in rows:
        near[a].append((b, w))
    return near, rows


def _nearest(near, source):
    dist, queue = {source: 0.0}, [(0.0, source)]
    while queue:
        d, u = heapq.heappop(queue)
        for v, w in near[u] if d == dist[u] else []:
            if d + w < dist.get(v, np.inf):
                dist[v] = d + w
                heapq.heappush(queue, (d + w, v))
    return dist


def _packed(near, rows, order):
    """Arcs in five runs, read in that order."""
    from arcloom.operators.search import Packed

    batch = lambda src, dst, weight: pa.RecordBatch.from_arrays([pa.array(src, pa.int64()), pa.array(dst, pa.int64()), pa.array(weight, pa.float64())], names=["src", "dst", "weight"])
    ids, cuts = list(near), np.linspace(0, len(rows), 6).astype(int)
    runs = [batch(*zip(*rows[cuts[i] : cuts[i + 1]], strict=True)) for i in order]
    return Packed([batch(ids[::2], [None] * len(ids[::2]), [1.0] * len(ids[::2])), *runs, batch(ids, [None] * len(ids), [None] * len(ids))], light_first=True)


@pytest.mark.parametrize("order", [(0, 1, 2, 3, 4), (3, 1, 4, 0, 2)])
def test_f1_distances_of_some_sources_at_a_time(order):
    from arcloom.operators.search import _distances

    near, rows = _graph(80)
    want = {(s, v): d for s in list(near)[::2] for v, d in _nearest(near, s).items()}
    for cells in (1, 300, 1 << 20):
        got = [row for c in _distances(_packed(near, rows, order), None, cells) for row in zip(*(x.tolist() for x in c), strict=True)]
        assert len(got) == len(want) and {(s, v): d for s, v, d in got} == want


def test_f1_few_arcs_of_a_dense_graph_are_tried(monkeypatch):
    """Arcs that lead beyond the farthest label are left out; each was tried once at least."""
    from arcloom.operators import search

    near, rows = _graph(200, some=400)
    packed, tried, slices = _packed(near, rows, range(5)), [], search.Packed.slices
    size = packed.reach()
    monkeypatch.setattr(packed, "reach", lambda: size)
    monkeypatch.setattr(search.Packed, "slices", lambda self, *a: (tried.append(len(x[-1])) or x for x in slices(self, *a)))
    list(search._distances(packed, None))
    assert 0 < sum(tried) < 0.75 * len(packed.marked) * len(rows)


def test_f1_sources_run_in_tasks_of_their_own(spark):
    """One task did all sources: a union of single partitions is a single partition."""
    from arcloom.model import PropertyGraph
    from arcloom.operators import search

    near, rows = _graph(80)
    g = PropertyGraph(spark.createDataFrame([(i, 0.5) for i in near], "id long, color double"), spark.createDataFrame(rows, "src long, dst long, weight double"))
    out = search.multi_source(g, g.vertices)
    assert out.groupBy(F.spark_partition_id()).count().count() == 4
    assert {(r.source, r.id): r.dist for r in out.collect()} == {(s, v): d for s in near for v, d in _nearest(near, s).items()}


def test_f2_dependencies_of_some_sources_at_a_time():
    """A path of 60 in gaps of ids, arcs in runs out of order: i (n - 1 - i) pairs go through vertex i, each from both ends."""
    from arcloom.operators.metrics import _dependencies

    near = {3 * i: [] for i in range(60)}
    rows = sorted((a, b, 1.0) for i in range(59) for a, b in ((3 * i, 3 * i + 3), (3 * i + 3, 3 * i)))
    packed = _packed(near, rows, (3, 1, 4, 0, 2))
    packed.marked = np.arange(60)
    for cells in (1, 200, 1 << 19):
        got = {i: x for c in _dependencies(packed, cells) for i, x in zip(*(x.tolist() for x in c), strict=True)}
        assert got == pytest.approx({3 * i: 2.0 * i * (59 - i) for i in range(1, 59)})


def test_f3_the_sample_goes_to_tasks_as_well(spark):
    """32 sources went by rounds of joins, two and more jobs a level; the scores are the same."""
    from arcloom.model import PropertyGraph
    from arcloom.operators import metrics, search
    from arcloom.plans.iterate import cut

    near, rows = _graph(60)
    g = PropertyGraph(spark.createDataFrame([(i, 0.5) for i in near], "id long, color double"), cut(spark.createDataFrame(rows, "src long, dst long, weight double")))
    few = cut(g.vertices.select("id").where("id < 96"))
    assert few.count() == 32 and search.Dealt.of(g, few)
    flow = metrics.flows(g, few).where("s <> src").groupBy(F.col("src").alias("id")).agg((F.sum("flow") / 2).alias("score"))
    want = {r.id: r.score for r in flow.collect()}
    assert {r.id: r.score for r in metrics.betweenness(g, few).collect()} == pytest.approx({i: want.get(i, 0.0) for i in near})
