"""Kernel 1: paths. Distances of all vertices from sources, and the searches this kernel stands for.

Only state moves: arcs are dealt by source once and kept. A round joins the vertices that just improved with
their arcs, takes the least offer a vertex, and accepts strict improvements, so every search ends when nothing
improves; rounds are not bounded unless a bound is asked for. A label is (distance, hops, predecessor) and the least one wins, so
predecessors lead to the source over arcs of weight zero too. A round writes the labels that improved, not the whole
state, which is put together again when what was added outgrows it. Weights are zero or more; a result has no row
for vertices that are not reached (``unreached``: rows with infinity or null instead).
"""

from __future__ import annotations

import heapq
import itertools
import tempfile
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from arcloom import rng
from arcloom.model import PropertyGraph, small
from arcloom.plans.iterate import Loop, cut, release
from arcloom.sources.ingest import GRAPHS, SEED, SQL, stored


@dataclass
class Searched:
    """Labels (source, id, d, hops, pred) and the trace: a row a round with the frontier, offers along arcs, and improved labels."""

    state: DataFrame
    trace: list[dict]
    converged: bool

    def work(self) -> dict[str, int]:
        """Counters over all rounds: what was shuffled (offers) and what was kept."""
        return {"rounds": len(self.trace), **{k: sum(t.get(k, 0) for t in self.trace) for k in ("frontier", "offers", "improved")}}


def _start(g: PropertyGraph, sources: DataFrame | list[int] | int) -> DataFrame:
    if isinstance(sources, DataFrame):
        return sources.select(F.col("id").cast("long").alias("source"), F.col("id").cast("long").alias("id"))
    ids = [sources] if isinstance(sources, int) else list(sources)
    return g.spark.createDataFrame([(i, i) for i in ids], "source long, id long")


KEY = ["source", "id"]


def _least(rows: DataFrame) -> DataFrame:
    """The least label of every vertex."""
    return rows.groupBy(*KEY).agg(F.min(F.struct("d", "hops", "pred")).alias("l")).select(*KEY, "l.d", "l.hops", "l.pred")


class _Labels:
    """Labels as a base table and what later rounds have improved."""

    def __init__(self, base: DataFrame, rows: int):
        self.tables, self.base_rows, self.added = [base], rows, 0

    def all(self) -> DataFrame:
        out = self.tables[0]
        for t in self.tables[1:]:
            out = out.unionByName(t)
        return out

    def add(self, improved: DataFrame, rows: int) -> None:
        self.tables.append(improved)
        self.added += rows
        if self.added > self.base_rows and len(self.tables) > 4:
            self.compact()

    def compact(self) -> DataFrame:
        if len(self.tables) > 1:
            new = cut(_least(self.all()))
            self.tables, self.base_rows, self.added = [new], new.count(), 0
        return self.tables[0]


def relax(g: PropertyGraph, sources, step, first: float | int, max_rounds: int | None = None, max_value: float | None = None, full: bool = False, target: int | None = None, delta: float | None = None) -> Searched:
    """Label correction keyed by (source, id). ``step(d, weight)`` is what an arc adds.

    ``full``: all reached vertices send each round. ``target``: offers over the target's present value are dropped.
    ``delta``: only improved vertices in the lowest bucket of that width send; the rest wait. ``max_rounds``: stop
    there; ``converged`` says whether that was the end.
    """
    arcs = g.arcs("weight")
    label = [F.lit(first).cast("double").alias("d"), F.lit(0).cast("long").alias("hops"), F.lit(None).cast("long").alias("pred")]
    base = cut(_start(g, sources).distinct().join(g.vertices.select("id"), "id", "left_semi").select(*KEY, *label))
    known, best = _Labels(base, base.count()), [None]

    def one(front: DataFrame, r: int):
        if delta is not None:
            front = cut(_least(front))
        sent = front.agg(F.count("*").alias("n"), F.min("d").alias("low")).first()
        if not sent["n"]:
            return front, {"frontier": 0, "offers": 0, "improved": 0}
        later = None
        if delta is not None:
            edge = (int(sent["low"] / delta) + 1) * delta
            front, later = front.where(F.col("d") < edge), front.where(F.col("d") >= edge)
        senders = known.compact() if full else front
        moves = small(senders.select("source", F.col("id").alias("src"), "d", "hops"), sent["n"], 32) if not full else senders.select("source", F.col("id").alias("src"), "d", "hops")
        offers = arcs.join(moves, "src").select("source", F.col("dst").alias("id"), step(F.col("d"), F.col("weight")).alias("d"), (F.col("hops") + 1).alias("hops"), F.col("src").alias("pred"))
        if max_value is not None:
            offers = offers.where(F.col("d") <= max_value)
        if best[0] is not None:
            offers = offers.where(F.col("d") <= best[0])
        offers = cut(offers.groupBy(*KEY).agg(F.min(F.struct("d", "hops", "pred")).alias("o"), F.count("*").alias("n")))
        made = offers.agg(F.count("*").alias("rows"), F.coalesce(F.sum("n"), F.lit(0)).alias("n"), F.min(F.when(F.col("id") == F.lit(target), F.col("o.d"))).alias("hit")).first()
        if made["hit"] is not None:
            best[0] = made["hit"] if best[0] is None else min(best[0], made["hit"])
        old = known.all().join(small(offers.select(*KEY), made["rows"]), KEY, "left_semi").groupBy(*KEY).agg(F.min(F.struct("d", "hops", "pred")).alias("l"))
        nearer = F.col("l").isNull() | (F.col("o.d") < F.col("l.d")) | ((F.col("o.d") == F.col("l.d")) & (F.col("o.hops") < F.col("l.hops")))
        better = offers.join(old, KEY, "left").where(F.col("l").isNull() | (F.col("o") < F.col("l")))
        improved = cut(better.select(*KEY, "o.d", "o.hops", "o.pred", nearer.alias("open")))
        rows = improved.count()
        release(offers)
        if rows:
            known.add(improved.drop("open"), rows)
        new = improved.where("open").drop("open")
        return new if later is None else new.unionByName(later), {"frontier": sent["n"], "offers": made["n"], "improved": rows}

    loop = Loop(one, lambda f: f["improved"] == 0 and (delta is None or f["frontier"] == 0), max_rounds)
    loop.run(base)
    arcs.unpersist()
    return Searched(known.compact(), loop.trace, loop.converged)


def sssp(g: PropertyGraph, source, engine: str = "frontier", delta: float = 0.25, max_rounds: int | None = None, max_dist: float | None = None, target: int | None = None, unreached: str = "absent") -> DataFrame:
    """(id, dist) from one source. Engines: frontier, full, bucketed, ordered. A bound on rounds or distance is a feature of the result; none is set by default."""
    if engine == "ordered":
        out = ordered(g, source)
    else:
        out = relax(g, source, lambda d, w: d + w, 0.0, max_rounds, max_dist, engine == "full", target, delta if engine == "bucketed" else None).state.select("id", F.col("d").alias("dist"))
    if unreached == "absent":
        return out
    fill = F.lit(float("inf")) if unreached == "inf" else F.lit(None).cast("double")
    return g.vertices.select("id").join(out, "id", "left").select("id", F.coalesce("dist", fill).alias("dist"))


def multi_source(g: PropertyGraph, sources, max_dist: float | None = None, max_rounds: int | None = None) -> DataFrame:
    """(source, id, dist) for every source. Many sources are dealt to tasks that each have the whole graph, if its arcs are few enough to map."""
    if max_rounds is None and (many := Dealt.of(g, _start(g, sources).select("id"))):
        return many.run("source long, id long, dist double", lambda packed: _distances(packed, max_dist))
    return relax(g, sources, lambda d, w: d + w, 0.0, max_rounds, max_dist).state.select("source", "id", F.col("d").alias("dist"))


def _distances(packed: Packed, most: float | None, cells: int = 1 << 20):
    """Columns (source, id, dist), some marked vertices at a time; the label of vertex v from the i-th of them is at i n + v.

    Of the vertices that wait, those go first that no other can improve over its lightest arc, so most go once. Arcs of a vertex
    are in order of weight: once a source has reached all it can, those that lead beyond its farthest label are left out.
    """
    n, size, most = len(packed), packed.reach(), np.inf if most is None else most
    least, any_ = np.full(n, np.inf), packed.degree > 0
    least[any_] = packed.weight[packed.start[:-1][any_]]
    group = max(1, cells // max(1, n))
    for at in range(0, len(packed.marked), group):
        s = packed.marked[at : at + group]
        dist, waits, tag = np.full(len(s) * n, np.inf), np.zeros(len(s) * n, bool), np.zeros(len(s) * n, np.int64)
        wait, left, top, work = np.arange(len(s)) * n + s, size[s] - 1, np.full(len(s), most), 0
        dist[wait] = 0.0
        while len(wait):
            of, v = np.divmod(wait, n)
            d, low, sure = dist[wait], np.full(len(s), np.inf), np.full(len(s), np.inf)
            np.minimum.at(low, of, d)
            np.minimum.at(sure, of, d + least[v])
            go = (d <= sure[of]) | (d - least[v] <= low[of])
            of, v, d, now, added = of[go], v[go], d[go], wait[go], [wait[~go]]
            waits[now] = False
            for a, b, many, arcs in packed.slices(v, packed.within(v, top[of] - d + 1e-12 * top[of])):
                to, offer = packed.to[arcs] + np.repeat(now[a:b] - v[a:b], many), packed.weight[arcs] + np.repeat(d[a:b], many)
                better = np.flatnonzero((offer < dist[to]) & (offer <= most))
                to, offer = to[better], offer[better]
                fresh = _once(to[np.flatnonzero(~waits[to])], tag)
                left -= np.bincount(fresh[np.isinf(dist[fresh])] // n, minlength=len(s))
                np.minimum.at(dist, to, offer)
                waits[fresh] = True
                added.append(fresh)
                work += len(arcs)
            wait = np.concatenate(added)
            if 8 * work > len(dist):
                rows, work = dist.reshape(-1, n)[left == 0], 0
                top[left == 0] = np.max(rows, 1, where=np.isfinite(rows), initial=0.0)
        for i in range(len(s)):
            found = np.flatnonzero(np.isfinite(dist[i * n : (i + 1) * n]))
            yield np.full(len(found), packed.ids[s[i]]), packed.ids[found], dist[i * n + found]


def _once(keys, tag):
    """Every key once; ``tag`` has a place for each."""
    at = np.arange(len(keys))
    tag[keys] = at
    return keys[np.flatnonzero(tag[keys] == at)]


_ARC = {"src": "long", "dst": "long", "weight": "double"}


def _runs(batches, most: int = 512):
    """Arcs as rows of packed columns, ``most`` arcs a row; Spark passes up to 10,000 rows at once."""
    import pyarrow as pa

    for b in batches:
        columns = [b[c].to_numpy(zero_copy_only=False) for c in _ARC]
        yield pa.RecordBatch.from_arrays([pa.array([x[i : i + most].tobytes() for i in range(0, len(x), most)], pa.binary()) for x in columns], names=[f"{c}s" for c in _ARC])


def _unpacked(batches):
    """Batches (src, dst, weight) of packed runs, and of vertices, which have no dst."""
    import pyarrow as pa

    for b in batches:
        ids = b.filter(b["src"].is_valid())
        yield pa.RecordBatch.from_arrays([ids["src"], pa.nulls(len(ids), pa.int64()), ids["weight"]], names=list(_ARC))
        runs = b.filter(b["src"].is_null())
        yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(b"".join(runs[f"{c}s"].to_pylist()), np.float64 if c == "weight" else np.int64)) for c in _ARC], names=list(_ARC))


@dataclass
class Dealt:
    """Sources dealt to tasks. A task reads the stored graph whole, in packed runs of sorted arcs, and keeps its arcs in a mapped file."""

    graph: PropertyGraph
    sources: DataFrame
    tasks: int

    #: With fewer sources, or with more arcs, rounds of joins are used.
    LEAST_SOURCES, MOST_ARCS = 16, 100_000_000

    @classmethod
    def of(cls, g: PropertyGraph, sources: DataFrame) -> Dealt | None:
        sources = cut(sources.distinct().join(g.vertices.select("id"), "id", "left_semi"))
        n = sources.count()
        if n < cls.LEAST_SOURCES:
            return None
        g = PropertyGraph(*(t if hasattr(t, "_cut_to") else cut(t) for t in (g.vertices, g.edges)))
        if g.edges.count() > cls.MOST_ARCS:
            return None
        arcs = g.edges.select(*(F.col(c).cast(kind).alias(c) for c, kind in _ARC.items())).repartitionByRange("src").sortWithinPartitions("src", "weight", "dst")
        g = PropertyGraph(g.vertices, cut(arcs.mapInArrow(_runs, "srcs binary, dsts binary, weights binary")))
        return cls(g, sources, min(max(1, g.spark.sparkContext.defaultParallelism), -(-n // 8)))

    def run(self, schema: str, work) -> DataFrame:
        """``work(packed) -> columns`` in every task; its sources are marked."""
        import pyarrow as pa
        from pyspark.sql.pandas.types import to_arrow_schema
        from pyspark.sql.types import _parse_datatype_string

        shape = to_arrow_schema(_parse_datatype_string(schema))

        def each(batches):
            for columns in work(Packed(_unpacked(batches), light_first=True)):
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, shape.types, strict=True)], names=shape.names)

        one_id = lambda mark: [F.col("id").cast("long").alias("src"), F.lit(mark).cast("double").alias("weight"), *(F.lit(None).cast("binary").alias(c) for c in ("srcs", "dsts", "weights"))]
        whole = self.graph.vertices.select(*one_id(None)).unionByName(self.graph.edges, allowMissingColumns=True)
        out = None
        for i in range(self.tasks):
            own = self.sources.where(F.pmod(F.xxhash64("id"), F.lit(self.tasks)) == i).select(*one_id(1.0))
            one = whole.unionByName(own).coalesce(1).mapInArrow(each, schema)
            out = one if out is None else out.unionByName(one)
        # A union of nothing but single partitions is made a single one by Spark 4.1, which is one task for all; this scan, which finds no row, keeps them apart.
        return out.unionByName(self.sources.where(F.pmod(F.xxhash64("id"), F.lit(self.tasks)) == self.tasks).select(*(F.lit(None).cast(f.dataType).alias(f.name) for f in out.schema.fields)))


def bfs(g: PropertyGraph, source, max_depth: int | None = None) -> DataFrame:
    """(id, level), to any depth unless a greatest one is given."""
    return relax(g, source, lambda d, w: d + 1, 0, max_depth).state.select("id", F.col("d").cast("int").alias("level"))


#: Arcs that a one-task engine takes at most if it holds rows of its own for them (Kruskal, Prim, grown parts).
MAX_LOCAL_ARCS = 5_000_000


def _slices(begin, many, most: int):
    """(a, b, many, arcs): the numbers from ``begin`` on, ``many`` each, of rows a to b; about ``most`` numbers at a time."""
    ends, a = np.cumsum(many), 0
    while a < len(many):
        done = ends[a - 1] if a else 0
        b = max(a + 1, int(np.searchsorted(ends, done + most, "right")))
        if ends[b - 1] > done:
            yield a, b, many[a:b], np.repeat(begin[a:b] - (ends[a:b] - done - many[a:b]), many[a:b]) + np.arange(ends[b - 1] - done)
        a = b


class Packed:
    """Adjacency of a whole graph in one task: vertices and offsets in memory, arcs in an unlinked file that is mapped.

    Reads as a dict of id -> [(neighbour, weight)] in order; ``start``, ``to`` (positions in ``ids``) and ``weight`` are the arrays.
    """

    def __init__(self, batches, light_first: bool = False):
        """Arrow batches (src, dst, weight); a vertex is a row without dst, again with a weight if it is marked.

        Arcs are in order of src, or are sorted runs: files are not always read one after the other. ``light_first``: those of a vertex end up in order of weight.
        """
        ids, marked, runs, n, raw = [np.zeros(0, np.int64)], [], [np.zeros((3, 0), np.int64)], 0, [tempfile.TemporaryFile() for _ in range(2)]
        for b in batches:
            src, arc = b["src"].to_numpy(zero_copy_only=False), b["dst"].is_valid()
            mask = arc.to_numpy(zero_copy_only=False)
            ids.append(src[~mask])
            marked.append(src[b["weight"].is_valid().to_numpy(zero_copy_only=False) & ~mask])
            src = src[mask]
            at = np.flatnonzero(np.concatenate([np.ones(min(1, len(src)), bool), src[1:] != src[:-1]]))
            runs.append(np.stack([src[at], n + at, np.diff(at, append=len(src))]))
            n += len(src)
            for f, name in zip(raw, ("dst", "weight"), strict=True):
                f.write(b[name].filter(arc).to_numpy(zero_copy_only=False).tobytes())
        self.ids = np.unique(np.concatenate(ids))
        self.marked = self._positions(np.unique(np.concatenate(marked))) if marked else self.ids
        of, begin, many = np.concatenate(runs, 1)
        of = self._positions(of)
        self.degree = np.bincount(of, many, len(self.ids)).astype(np.int64)
        self.start = np.concatenate([[0], np.cumsum(self.degree)])
        dst, self.weight = (self._mapped(f, kind) for f, kind in zip(raw, (np.int64, np.float64), strict=True))
        if mixed := (of[1:] < of[:-1]).any():
            order = np.argsort(of, kind="stable")
            begin, many = begin[order], many[order]
        parts = [arcs for *_, arcs in _slices(begin, many, 1 << 20)] if mixed else [slice(i, i + (1 << 20)) for i in range(0, n, 1 << 20)]
        kind = np.int32 if len(self.ids) < 1 << 31 else np.int64
        self.to = self._copied((self._positions(dst[p]).astype(kind) for p in parts), kind)
        if mixed:
            self.weight = self._copied((self.weight[p] for p in parts), np.float64)
        if light_first:
            for i in range(0, n, 1 << 20):
                w = self.weight[i : i + (1 << 20) + 1]
                falls = i + 1 + np.flatnonzero(w[1:] < w[:-1])
                of = np.searchsorted(self.start, falls, "right") - 1
                for v in np.unique(of[falls > self.start[of]]).tolist():
                    own = slice(self.start[v], self.start[v + 1])
                    order = np.argsort(self.weight[own], kind="stable")
                    self.to[own], self.weight[own] = self.to[own][order], self.weight[own][order]
        self.at = {v: i for i, v in enumerate(self.ids.tolist())}

    @classmethod
    def _copied(cls, parts, kind):
        with tempfile.TemporaryFile() as f:
            for p in parts:
                f.write(p.tobytes())
            return cls._mapped(f, kind)

    @staticmethod
    def _mapped(f, kind):
        f.flush()
        return np.memmap(f, kind, "r+") if f.tell() else np.zeros(0, kind)

    def _positions(self, ids):
        at = np.searchsorted(self.ids, ids)
        if len(ids) and (not len(self.ids) or (self.ids[np.minimum(at, len(self.ids) - 1)] != ids).any()):
            raise KeyError("an arc ends at no vertex")
        return at

    def __len__(self):
        return len(self.ids)

    def __iter__(self):
        return iter(self.at)

    def __contains__(self, v):
        return v in self.at

    def near(self, v):
        """Positions of the neighbours of v."""
        i = self.at[v]
        return self.to[self.start[i] : self.start[i + 1]]

    def __getitem__(self, v):
        i = self.at[v]
        a, b = self.start[i], self.start[i + 1]
        return list(zip(self.ids[self.to[a:b]].tolist(), self.weight[a:b].tolist(), strict=True))

    def items(self):
        return ((v, self[v]) for v in self.at)

    def slices(self, front, many=None, most: int = 1 << 17):
        """``_slices`` of the first arcs, or all, of the positions in ``front``."""
        return _slices(self.start[front], self.degree[front] if many is None else many, most)

    def within(self, front, most):
        """How many arcs of each position weigh its ``most`` at most; they are in order of weight."""
        low, high = self.start[front], self.start[front + 1]
        bound = np.flatnonzero(np.isfinite(most) & (low < high))
        a, b, most = low[bound], high[bound], most[bound]
        while (a < b).any():
            mid = (a + b) // 2
            up = (a < b) & (self.weight[np.minimum(mid, len(self.weight) - 1)] <= most)
            a, b = np.where(up, mid + 1, a), np.where(up, b, mid)
        high[bound] = a
        return high - low

    def reach(self):
        """A number a vertex: how many vertices a marked one reaches, itself included. Arcs go both ways."""
        size, seen = np.zeros(len(self), np.int64), np.zeros(len(self), bool)
        for s in self.marked.tolist():
            if seen[s]:
                continue
            front, part, seen[s] = np.array([s]), [], True
            while len(front):
                part.append(front)
                near = [front[:0]]
                for *_, arcs in self.slices(front):
                    to = self.to[arcs]
                    near.append(np.unique(to[~seen[to]]).astype(np.int64))
                    seen[near[-1]] = True
                front = np.concatenate(near)
            part = np.concatenate(part)
            size[part] = len(part)
        return size


def local(g: PropertyGraph, schema: str, work, most: int | None = MAX_LOCAL_ARCS) -> DataFrame:
    """Run ``work(adjacency) -> rows`` over the whole graph in one task, arcs in a mapped file; with ``most`` a graph over so many arcs is refused."""
    import pyarrow as pa
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import _parse_datatype_string

    if most is not None and (n := g.edges.count()) > most:
        raise ValueError(f"{n} arcs are over max_local_arcs={most}; use a distributed engine")
    shape = to_arrow_schema(_parse_datatype_string(schema))

    def run(batches):
        rows = iter(work(Packed(batches)))
        while some := list(itertools.islice(rows, 1 << 16)):
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*some, strict=True), shape.types, strict=True)], names=shape.names)

    vertex = g.vertices.select(F.col("id").cast("long").alias("src"), F.lit(None).cast("long").alias("dst"), F.lit(None).cast("double").alias("weight"))
    arcs = g.edges.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"), F.col("weight").cast("double").alias("weight"))
    return vertex.unionByName(arcs).repartition(1).sortWithinPartitions("src", "dst", "weight").mapInArrow(run, schema)


def ordered(g: PropertyGraph, source: int, most: int | None = None) -> DataFrame:
    """The queue in order: the nearest vertex is settled first. One task."""

    def work(adjacent):
        dist, queue = {source: 0.0} if source in adjacent else {}, [(0.0, source)] if source in adjacent else []
        done = set()
        while queue:
            d, u = heapq.heappop(queue)
            if u in done:
                continue
            done.add(u)
            for v, w in adjacent[u]:
                if d + w < dist.get(v, float("inf")):
                    dist[v] = d + w
                    heapq.heappush(queue, (d + w, v))
        return dist.items()

    return local(g, "id long, dist double", work, most)


def dfs(g: PropertyGraph, source: int, most: int | None = None) -> DataFrame:
    """(id, position, parent) in depth-first order, smaller ids first. One task: the order is sequential. The stack holds a vertex and its next arc."""

    def work(adjacent):
        if source not in adjacent:
            return
        ids, start, to = adjacent.ids.tolist(), adjacent.start.tolist(), adjacent.to
        seen, at, first = bytearray(len(ids)), 1, adjacent.at[source]
        stack = [[first, start[first]]]
        seen[first] = 1
        yield source, 0, -1
        while stack:
            top = stack[-1]
            u, a = top
            chunk = to[a : min(a + 256, start[u + 1])].tolist()
            for k, v in enumerate(chunk):
                if not seen[v]:
                    seen[v] = 1
                    yield ids[v], at, ids[u]
                    at += 1
                    top[1] = a + k + 1
                    stack.append([v, start[v]])
                    break
            else:
                top[1] = a + len(chunk)
                if top[1] == start[u + 1]:
                    stack.pop()

    return local(g, "id long, position long, parent long", work, most)


def components(g: PropertyGraph) -> DataFrame:
    """(id, component): the smallest id that is reached. Labels jump to the label of their label each round."""
    arcs = g.arcs()
    state = cut(g.vertices.select("id", F.col("id").alias("c")))

    def one(state: DataFrame, r: int):
        offers = arcs.join(state.select(F.col("id").alias("src"), "c"), "src").groupBy(F.col("dst").alias("id")).agg(F.min("c").alias("o"))
        low = state.join(offers, "id", "left").select("id", "c", F.least("c", F.coalesce("o", "c")).alias("n"))
        jump = state.select(F.col("id").alias("n"), F.col("c").alias("j"))
        new = cut(low.join(jump, "n").select("id", F.least("n", "j").alias("c"), (F.least("n", "j") < F.col("c")).alias("moved")))
        return new.select("id", "c"), {"moved": new.where("moved").count()}

    loop = Loop(one, lambda f: f["moved"] == 0)
    state = loop.run(state)
    arcs.unpersist()
    return state.select("id", F.col("c").alias("component"))


def msf(g: PropertyGraph, engine: str = "boruvka") -> DataFrame:
    """Edges (src < dst, weight) of a minimum spanning forest; ties by (weight, src, dst), so all engines agree."""
    if engine in ("kruskal", "prim"):
        return local(g, "src long, dst long, weight double", _kruskal if engine == "kruskal" else _prim)
    edges = cut(g.edges.where("src < dst").select("src", "dst", "weight", F.col("src").alias("a"), F.col("dst").alias("b")))
    chosen = None
    while True:
        ends = edges.select(F.explode(F.array("a", "b")).alias("c"), F.struct("weight", "src", "dst", "a", "b").alias("e"))
        light = cut(ends.groupBy("c").agg(F.min("e").alias("e")).select("e.*").distinct())
        if light.isEmpty():
            break
        chosen = light.select("src", "dst", "weight") if chosen is None else chosen.unionByName(light.select("src", "dst", "weight"))
        roots = _roots(ends.groupBy("c").agg(F.min("e").alias("e")).select("c", F.when(F.col("e.a") == F.col("c"), F.col("e.b")).otherwise(F.col("e.a")).alias("p")))
        roots = small(roots, roots.count())
        for end in ("a", "b"):
            edges = edges.join(roots.select(F.col("c").alias(end), "p"), end, "left").withColumn(end, F.coalesce("p", end)).drop("p")
        # Of parallel edges between two trees only the lightest can be chosen.
        lightest = edges.where("a <> b").groupBy(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).agg(F.min(F.struct("weight", "src", "dst")).alias("e"))
        edges = cut(lightest.select("e.weight", "e.src", "e.dst", "a", "b"))
    return chosen.distinct() if chosen is not None else g.edges.where("src < dst").select("src", "dst", "weight")


def _roots(parents: DataFrame) -> DataFrame:
    """(c, p) with p the root: two that chose each other meet at the smaller, then parents jump to their parents."""
    p = cut(parents)
    back = p.select(F.col("c").alias("p"), F.col("p").alias("q"))
    p = cut(p.join(back, "p").select("c", F.when((F.col("q") == F.col("c")) & (F.col("c") < F.col("p")), F.col("c")).otherwise(F.col("p")).alias("p")))
    while True:
        up = p.select(F.col("c").alias("p"), F.col("p").alias("q"))
        new = cut(p.join(up, "p").select("c", F.col("q").alias("p"), (F.col("q") != F.col("p")).alias("moved")))
        p = new.select("c", "p")
        if new.where("moved").isEmpty():
            break
    return p


def _kruskal(adjacent):
    root = {i: i for i in adjacent}

    def find(x):
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    for w, s, d in sorted((w, s, d) for s, row in adjacent.items() for d, w in row if s < d):
        a, b = find(s), find(d)
        if a != b:
            root[max(a, b)] = min(a, b)
            yield s, d, w


def _prim(adjacent):
    seen = set()
    for first in adjacent:
        if first in seen:
            continue
        seen.add(first)
        heap = [(w, min(first, d), max(first, d), d) for d, w in adjacent[first]]
        heapq.heapify(heap)
        while heap:
            w, s, d, new = heapq.heappop(heap)
            if new in seen:
                continue
            seen.add(new)
            yield s, d, w
            for x, wx in adjacent[new]:
                if x not in seen:
                    heapq.heappush(heap, (wx, min(new, x), max(new, x), x))


def path_tree(g: PropertyGraph, source) -> DataFrame:
    """(id, dist, hops, pred): of the shortest paths those of fewest arcs, of these the smallest predecessor; the source has none."""
    return relax(g, source, lambda d, w: d + w, 0.0).state.select("id", F.col("d").alias("dist"), "hops", "pred")


def paths(g: PropertyGraph, source, targets: list[int]) -> DataFrame:
    """(target, path, dist) by walking predecessors back, all targets at once, as far as the longest path goes."""
    tree = cut(path_tree(g, source))
    walk = cut(tree.where(F.col("id").isin(targets)).select(F.col("id").alias("target"), "dist", F.array("id").alias("path"), F.col("pred").alias("next")))
    while not walk.where("next is not null").isEmpty():
        new = cut(walk.join(tree.select(F.col("id").alias("next"), F.col("pred").alias("after")), "next", "left").select("target", "dist", F.when(F.col("next").isNull(), F.col("path")).otherwise(F.concat(F.array("next"), "path")).alias("path"), F.col("after").alias("next")))
        release(walk)
        walk = new
    return walk.select("target", "path", "dist")


def _graph(name: str, spark: SparkSession, sf_dir: str) -> PropertyGraph:
    return stored(GRAPHS[name](spark, sf_dir))


def least_id(g: PropertyGraph) -> int:
    return g.edges.agg(F.min("src")).first()[0]


def hub(g: PropertyGraph) -> int:
    """The vertex of highest degree, the smallest of several."""
    return g.edges.groupBy("src").count().orderBy(F.desc("count"), "src").first()["src"]


def _dist(name: str, pick=least_id, **options):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        g = _graph(name, spark, sf_dir)
        return sssp(g, pick(g), **options).select("id", F.round("dist", 6).alias("dist"))

    return run


def k1_bfs_levels(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = _graph("copart", spark, sf_dir)
    return bfs(g, least_id(g)).groupBy("level").agg(F.count("*").alias("n"))


def k1_dfs_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = _graph("userseq", spark, sf_dir)
    return dfs(g, least_id(g))


def k1_msf_weight(spark: SparkSession, sf_dir: str) -> DataFrame:
    return msf(_graph("copart", spark, sf_dir)).agg(F.count("*").alias("edges"), F.round(F.sum("weight"), 6).alias("weight"))


def _tree(name: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        g = _graph(name, spark, sf_dir)
        return path_tree(g, least_id(g)).select("id", F.round("dist", 6).alias("dist"), "hops", F.coalesce("pred", F.lit(-1)).alias("pred"))

    return run


def k1_paths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Paths to all suppliers of the forest that the first region reaches: length, ends, and how many arcs."""
    g = _graph("geo", spark, sf_dir)
    targets = [r["id"] for r in g.vertices.where("id % 8 = 1").select("id").collect()]
    return paths(g, least_id(g), targets).select("target", F.round("dist", 6).alias("dist"), F.concat_ws("-", "path").alias("path"))


def k1_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The smallest id, the hub, and eight drawn ids as sources: reached vertices, largest and mean distance."""
    g = _graph("userseq", spark, sf_dir)
    drawn = [r["id"] for r in g.vertices.select("id", rng.bits(SEED, "source", "id").alias("r")).orderBy("r", "id").limit(8).collect()]
    d = multi_source(g, sorted({least_id(g), hub(g), *drawn}))
    return d.groupBy("source").agg(F.count("*").alias("reached"), F.round(F.max("dist"), 6).alias("farthest"), F.round(F.avg("dist"), 6).alias("mean"))


def measure_search_work(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rounds, offers along arcs and improved labels of the engines on one graph, against its arcs."""
    g = _graph("userseq", spark, sf_dir)
    n, rows = g.edges.count(), []
    for engine, options in (("frontier", {}), ("full", {"full": True}), ("bucketed", {"delta": 0.05})):
        w = relax(g, least_id(g), lambda d, w: d + w, 0.0, **options).work()
        rows.append((engine, n, w["rounds"], w["offers"], w["improved"]))
    return spark.createDataFrame(rows, "engine string, arcs long, rounds long, offers long, improved long")


def k1_multi_source(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = _graph("cosupp", spark, sf_dir)
    return multi_source(g, g.vertices.where("color > 0.9")).select("source", "id", F.round("dist", 6).alias("dist"))


def k1_within(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = _graph("copart", spark, sf_dir)
    return sssp(g, least_id(g), max_dist=1.0).select("id", F.round("dist", 6).alias("dist"))


def k1_components(spark: SparkSession, sf_dir: str) -> DataFrame:
    return components(_graph("docline", spark, sf_dir))


QUERIES = {
    "k1_sssp_copart": _dist("copart"),
    "k1_sssp_geo": _dist("geo"),
    "k1_sssp_words": _dist("words", hub),
    "k1_sssp_full": _dist("userseq", engine="full"),
    "k1_sssp_bucketed": _dist("copart", engine="bucketed", delta=0.25),
    "k1_sssp_ordered": _dist("userseq", engine="ordered"),
    "k1_bfs_levels": k1_bfs_levels,
    "k1_dfs_order": k1_dfs_order,
    "k1_msf_weight": k1_msf_weight,
    "k1_path_tree": _tree("geo"),
    "k1_path_tree_zero": _tree("partsupp"),
    "k1_paths": k1_paths,
    "k1_sources": k1_sources,
    "measure_search_work": measure_search_work,
    "k1_multi_source": k1_multi_source,
    "k1_within": k1_within,
    "k1_components": k1_components,
}

_LEAST, _HUB = "SELECT min(src) AS id FROM e", "SELECT src AS id FROM e GROUP BY 1 ORDER BY count(*) DESC, 1 LIMIT 1"


def _sp(graph: str, source: str = _LEAST, bound: str = "", add: str = "weight") -> str:
    return f"WITH RECURSIVE {SQL[graph]}, s0 AS ({source}), sp(id, dist) USING KEY (id) AS (SELECT id, 0.0::DOUBLE FROM s0 UNION SELECT e.dst, min(sp.dist + {add}) FROM sp JOIN e ON e.src = sp.id LEFT JOIN recurring.sp AS r ON r.id = e.dst WHERE (r.dist IS NULL OR sp.dist + {add} < r.dist) {bound} GROUP BY e.dst)"


def _label(graph: str) -> str:
    """Relation l(id, d, hops): distances, and the fewest arcs of a shortest path."""
    return _sp(graph) + ", tight AS MATERIALIZED (SELECT e.src, e.dst FROM e JOIN sp a ON a.id = e.src JOIN sp b ON b.id = e.dst WHERE a.dist + e.weight = b.dist), h(id, hops) USING KEY (id) AS (SELECT id, 0 FROM s0 UNION SELECT tight.dst, min(h.hops + 1) FROM h JOIN tight ON tight.src = h.id LEFT JOIN recurring.h AS r ON r.id = tight.dst WHERE r.hops IS NULL OR h.hops + 1 < r.hops GROUP BY 1), l AS MATERIALIZED (SELECT sp.id, dist AS d, hops::BIGINT AS hops FROM sp JOIN h ON h.id = sp.id)"


_PRED = " SELECT l.id, round(l.d, 6) AS dist, l.hops, coalesce(min(p.id), -1) AS pred FROM l LEFT JOIN e ON e.dst = l.id LEFT JOIN l p ON p.id = e.src AND p.d + e.weight = l.d AND p.hops + 1 = l.hops GROUP BY 1, 2, 3"
_ROUND = " SELECT id, round(dist, 6) AS dist FROM sp"
ORACLES = {
    "k1_sssp_copart": _sp("copart") + _ROUND,
    "k1_sssp_geo": _sp("geo") + _ROUND,
    "k1_sssp_words": _sp("words", _HUB) + _ROUND,
    "k1_sssp_full": _sp("userseq") + _ROUND,
    "k1_sssp_bucketed": _sp("copart") + _ROUND,
    "k1_sssp_ordered": _sp("userseq") + _ROUND,
    "k1_bfs_levels": _sp("copart", add="1") + " SELECT dist::INTEGER AS level, count(*) AS n FROM sp GROUP BY 1",
    "k1_path_tree": _label("geo") + _PRED,
    "k1_path_tree_zero": _label("partsupp") + _PRED,
    "k1_paths": _label("geo") + ", t AS (SELECT l.id, min(e.src) AS pred FROM l JOIN e ON e.dst = l.id JOIN l p ON p.id = e.src AND p.d + e.weight = l.d AND p.hops + 1 = l.hops GROUP BY 1), w(target, here, path) AS (SELECT id, id, id::VARCHAR FROM l WHERE id % 8 = 1 UNION ALL SELECT target, pred, pred::VARCHAR || '-' || path FROM w JOIN t ON t.id = w.here) SELECT target, round(l.d, 6) AS dist, path FROM w JOIN l ON l.id = target WHERE here IN (SELECT id FROM s0)",
    "k1_sources": f"WITH RECURSIVE {SQL['userseq']}, s0 AS ({_LEAST} UNION SELECT * FROM ({_HUB}) UNION SELECT * FROM (SELECT id FROM v ORDER BY {rng.sql_bits(SEED, 'source', 'id')}, id LIMIT 8)), sp(source, id, dist) USING KEY (source, id) AS (SELECT id, id, 0.0::DOUBLE FROM s0 UNION SELECT sp.source, e.dst, min(sp.dist + weight) FROM sp JOIN e ON e.src = sp.id LEFT JOIN recurring.sp AS r ON r.id = e.dst AND r.source = sp.source WHERE r.dist IS NULL OR sp.dist + weight < r.dist GROUP BY 1, 2) SELECT source, count(*) AS reached, round(max(dist), 6) AS farthest, round(avg(dist), 6) AS mean FROM sp GROUP BY 1",
    "k1_within": _sp("copart", bound="AND sp.dist + weight <= 1.0") + _ROUND,
    "k1_multi_source": f"WITH RECURSIVE {SQL['cosupp']}, sp(source, id, dist) USING KEY (source, id) AS (SELECT id, id, 0.0::DOUBLE FROM v WHERE color > 0.9 UNION SELECT sp.source, e.dst, min(sp.dist + weight) FROM sp JOIN e ON e.src = sp.id LEFT JOIN recurring.sp AS r ON r.id = e.dst AND r.source = sp.source WHERE r.dist IS NULL OR sp.dist + weight < r.dist GROUP BY 1, 2) SELECT source, id, round(dist, 6) AS dist FROM sp",
    "k1_components": f"WITH RECURSIVE {SQL['docline']}, c(id, component) USING KEY (id) AS (SELECT id, id FROM v UNION SELECT e.dst, min(c.component) FROM c JOIN e ON e.src = c.id JOIN recurring.c AS r ON r.id = e.dst WHERE c.component < r.component GROUP BY 1) SELECT id, component FROM c",
}
