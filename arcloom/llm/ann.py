"""Approximate nearest neighbours by learned partitions.

A bounded sample (``sample`` vectors with the smallest hash of their id, documented parameter) is fitted on the driver:
its exact neighbour graph is cut into parts of equal size by refinement that moves a vector to the part of most of
its neighbours while there is room, and a small network learns from a vector the shares of its neighbours by part.
The network then places every vector of the table in its most probable part and routes a query to its most probable
parts; how many it takes for the target recall is measured on sampled queries that the network was not fitted on.
Candidates of those parts are scored exactly, in double precision.

There are about as many parts as the square root of the number of vectors, bounded by the sample. Small parts are
stored together in a bundle of at most ``chunk`` vectors, so that a query travels once a bundle; a larger part is
dealt by a hash of the id into chunks, so one that a repeated vector fills is many chunks. Chunk and query block meet in
one task, where a query meets its probed parts only, and leave the nearest of each query.

Vectors that are null, zero, or hold null or non-finite components, and vectors whose length is not the most frequent
one, take no part. A repeated id is a row each as a candidate and one query, and is never its own neighbour. Fewer
candidates than asked: all of them. Ties in score go to the smaller id. Empty table: no rows. Other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import materialise, table


@dataclass
class Router:
    """A linear classifier with one hidden layer beside it. ``weights``: direct, into and out of the hidden layer, and the two biases."""

    weights: tuple[np.ndarray, ...]
    probes: int
    recall: float

    @property
    def parts(self) -> int:
        return self.weights[0].shape[1]

    def logits(self, x: np.ndarray) -> np.ndarray:
        direct, into, out, bias, last = self.weights
        x = x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-30)
        return x @ direct + np.maximum(x @ into + bias, 0) @ out + last

    def order(self, x: np.ndarray) -> np.ndarray:
        return np.argsort(-self.logits(x), axis=1, kind="stable")


def neighbour_graph(x: np.ndarray, k: int, block: int = 64) -> np.ndarray:
    """The k nearest of every row, ``block`` rows at a time; only what is kept outlives a block."""
    out, far = np.empty((len(x), k), np.int64), -x.T
    for a in range(0, len(x), block):
        s = x[a : a + block] @ far
        s[np.arange(len(s)), a + np.arange(len(s))] = np.inf
        out[a : a + block] = np.argpartition(s, k - 1, axis=1)[:, :k]
    return out


def balanced_parts(x: np.ndarray, near: np.ndarray, parts: int, sweeps: int = 8, slack: float = 1.05) -> np.ndarray:
    """Label every vertex; no part is larger than ``slack`` times an even share."""
    dice, n = np.random.default_rng(3), len(near)
    label = np.empty(n, np.int64)
    todo = [(np.arange(n), 0, parts)]
    while todo:  # start: halves along the line between two means
        ids, first, count = todo.pop()
        if count == 1:
            label[ids] = first
            continue
        way = dice.standard_normal(x.shape[1])
        for _ in range(5):
            side = x[ids] @ way
            high = side > np.median(side)
            way = x[ids][high].mean(0) - x[ids][~high].mean(0) if high.any() else way
        ids = ids[np.argsort(x[ids] @ way, kind="stable")]
        cut = len(ids) * (count // 2) // count
        todo += [(ids[:cut], first, count // 2), (ids[cut:], first + count // 2, count - count // 2)]
    room = int(np.ceil(slack * n / parts)) - np.bincount(label, minlength=parts)
    back: list[list[int]] = [[] for _ in range(n)]
    for i, row in enumerate(near.tolist()):
        for j in row:
            back[j].append(i)
    both = [np.array(near[i].tolist() + back[i]) for i in range(n)]
    for _ in range(sweeps):
        moved = 0
        for i in dice.permutation(n).tolist():
            votes = np.bincount(label[both[i]], minlength=parts)
            own = label[i]
            votes[(room <= 0) & (np.arange(parts) != own)] = -1
            to = int(votes.argmax())
            if votes[to] > votes[own]:
                room[own] += 1
                room[to] -= 1
                label[i] = to
                moved += 1
        if moved < n // 200:
            break
    return label


def fit_router(x: np.ndarray, parts: int, k: int = 20, hidden: int = 64, epochs: int = 10, target: float = 0.94, queries: int = 1024) -> Router:
    """Parts are fitted whenever there are two; fewer vectors than parts make fewer parts. ``probes`` is the least number that reaches the target on held-out vectors."""
    dim, parts = (x.shape[1] if x.ndim == 2 else 1), max(1, min(parts, len(x) // 2))
    if parts < 2:
        return Router((np.zeros((dim, 1)), np.zeros((dim, 1)), np.zeros((1, 1)), np.zeros(1), np.zeros(1)), 1, 1.0)
    x = x / np.linalg.norm(x, axis=1, keepdims=True)
    near = neighbour_graph(x, min(k, len(x) - 1))
    label = balanced_parts(x, near, parts)
    goal = np.stack([np.bincount(row, minlength=parts) for row in np.concatenate([label[near], label[:, None]], 1)]).astype(float)
    goal /= goal.sum(1, keepdims=True)
    dice = np.random.default_rng(4)
    order = dice.permutation(len(x))
    held, own = order[: min(queries, len(x) // 4)], order[min(queries, len(x) // 4) :]
    centre = np.stack([x[label == p].sum(0) for p in range(parts)])
    centre /= np.maximum(np.linalg.norm(centre, axis=1, keepdims=True), 1e-30)
    params = [8.0 * centre.T, dice.standard_normal((dim, hidden)) / np.sqrt(dim), np.zeros((hidden, parts)), np.zeros(hidden), np.zeros(parts)]
    first, second = ([np.zeros_like(p) for p in params] for _ in range(2))
    for t in range(1, 1 + epochs * -(-len(own) // 256)):
        ix = own[dice.integers(0, len(own), 256)]
        h = np.maximum(x[ix] @ params[1] + params[3], 0)
        z = x[ix] @ params[0] + h @ params[2] + params[4]
        p = np.exp(z - z.max(1, keepdims=True))
        g = (p / p.sum(1, keepdims=True) - goal[ix]) / len(ix)
        gh = (g @ params[2].T) * (h > 0)
        for i, grad in enumerate((x[ix].T @ g, x[ix].T @ gh, h.T @ g, gh.sum(0), g.sum(0))):
            first[i] = 0.9 * first[i] + 0.1 * grad
            second[i] = 0.99 * second[i] + 0.01 * grad**2
            params[i] -= 0.01 * (first[i] / (1 - 0.9**t)) / (np.sqrt(second[i] / (1 - 0.99**t)) + 1e-8)
    router = Router(tuple(params), parts, 1.0)
    placed, routed = router.order(x)[:, 0], router.order(x[held])
    rank = np.empty_like(routed)
    np.put_along_axis(rank, routed, np.arange(parts)[None, :].repeat(len(held), 0), 1)
    needed = np.take_along_axis(rank, placed[near[held]], 1)
    reached = np.cumsum(np.bincount(needed.ravel(), minlength=parts)) / needed.size
    router.probes = int(np.argmax(reached >= target)) + 1
    router.recall = float(reached[router.probes - 1])
    return router


def valid_vectors(rows: DataFrame, id_col: str, vector_col: str) -> tuple[DataFrame, int]:
    """(id, v array<double>) of the vectors that take part, and their number."""
    v = F.col("v")
    fine = rows.select(F.col(id_col).cast("long").alias("id"), F.col(vector_col).cast("array<double>").alias("v")).where(F.col("id").isNotNull() & v.isNotNull() & F.forall(v, lambda a: a.isNotNull() & ~F.isnan(a) & (F.abs(a) < F.lit(float("inf")))) & F.exists(v, lambda a: a != 0))
    lengths = fine.groupBy(F.size("v").alias("n")).count().orderBy(F.desc("count"), "n").limit(1).collect()
    return fine.where(F.size("v") == (lengths[0]["n"] if lengths else 0)), lengths[0]["count"] if lengths else 0


def _matrix(column: pa.ChunkedArray | pa.Array) -> np.ndarray:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return column.flatten().to_numpy().reshape(len(column), -1)


def _place(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                x = _matrix(batch.column("v"))
                yield pa.RecordBatch.from_pydict({"part": pa.array(shared.value.order(x)[:, 0], pa.int32()), "id": batch.column("id"), "v": pa.array([r.tobytes() for r in x], pa.binary())})

    return run


def _route(shared, least: int):
    """A row for every query and bundle that it probes, with the parts probed there. Parts are taken until they hold ``least`` vectors, if the usual number does not."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        router, bundle, sizes = shared.value
        for batch in batches:
            if not batch.num_rows:
                continue
            x = _matrix(batch.column("v"))
            order = router.order(x)
            enough = (np.cumsum(sizes[order], 1) < least).sum(1) + 1
            row, at = np.nonzero(np.arange(router.parts)[None, :] < np.maximum(enough, router.probes)[:, None])
            part = order[row, at]
            held = sizes[part] > 0
            row, part = row[held], part[held]
            by = np.lexsort((part, bundle[part], row))
            row, part = row[by], part[by]
            first = np.flatnonzero(np.diff(row, prepend=-1) | np.diff(bundle[part], prepend=-1))
            yield pa.RecordBatch.from_pydict({"bundle": pa.array(bundle[part[first]], pa.int32()), "id": batch.column("id").take(pa.array(row[first])), "v": pa.array([x[i].tobytes() for i in row[first]], pa.binary()), "probed": pa.array([p.astype("<i4").tobytes() for p in np.split(part, first[1:])] if len(first) else [], pa.binary())})

    return run


def _block(rows: pa.Table) -> pa.Table:
    """Vectors of a chunk in the order of their parts."""
    part = rows.column("part").to_numpy()
    order = np.argsort(part, kind="stable")
    ids, v = rows.column("id").to_numpy(), rows.column("v").to_pylist()
    return pa.table({"bundle": rows.column("bundle").slice(0, 1), "chunk": rows.column("chunk").slice(0, 1), "ids": pa.array([ids[order].astype("<i8").tobytes()], pa.binary()), "parts": pa.array([part[order].astype("<i4").tobytes()], pa.binary()), "block": pa.array([b"".join(v[i] for i in order)], pa.binary())})


def _query_block(rows: pa.Table) -> pa.Table:
    probed = rows.column("probed").to_pylist()
    return pa.table({"bundle": rows.column("bundle").slice(0, 1), "q_ids": pa.array([rows.column("id").to_numpy().astype("<i8").tobytes()], pa.binary()), "q_block": pa.array([b"".join(rows.column("v").to_pylist())], pa.binary()), "q_many": pa.array([np.array([len(p) // 4 for p in probed], "<i4").tobytes()], pa.binary()), "q_parts": pa.array([b"".join(probed)], pa.binary())})


def nearest(ids: np.ndarray, x: np.ndarray, query: int, q: np.ndarray, rough: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Ids and exact scores of the k nearest; ties to the smaller id. ``rough`` may err in the last digits and is -inf where a vector is no candidate."""
    rough = np.where(ids == query, -np.inf, rough)
    held = np.flatnonzero(rough > -np.inf)
    if len(held) > k:
        least = np.partition(rough, -k)[-k]
        held = np.flatnonzero(rough >= least - 1e-9 * max(1.0, abs(least)))
    score = (x[held] * q).sum(axis=1)
    top = np.lexsort((ids[held], -score))[:k]
    return ids[held][top], score[top]


def _rerank(dim: int, k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                get = lambda c, kind, i=i, batch=batch: np.frombuffer(batch.column(c)[i].as_py(), kind)
                ids, parts, x = get("ids", "<i8"), get("parts", "<i4"), get("block", "<f8").reshape(-1, dim)
                queries, q = get("q_ids", "<i8"), get("q_block", "<f8").reshape(-1, dim)
                asked, who = get("q_parts", "<i4"), np.repeat(np.arange(len(queries)), get("q_many", "<i4"))
                for a in range(0, len(queries), 256):
                    n = min(256, len(queries) - a)
                    rough = np.full((n, len(x)), -np.inf)
                    here = (who >= a) & (who < a + n)
                    for p in np.unique(asked[here]):
                        begin, end = np.searchsorted(parts, [p, p + 1])
                        if begin < end:
                            mine = who[here & (asked == p)] - a
                            rough[mine, begin:end] = q[a + mine] @ x[begin:end].T
                    found = [nearest(ids, x, int(queries[a + j]), q[a + j], rough[j], k) for j in range(n)]
                    yield pa.RecordBatch.from_pydict({"query_id": pa.array(np.repeat(queries[a : a + n], [len(f[0]) for f in found]), pa.int64()), "vec_id": pa.array(np.concatenate([f[0] for f in found]), pa.int64()), "score": pa.array(np.concatenate([f[1] for f in found]), pa.float64())})

    return run


@dataclass
class Index:
    """``blocks`` are chunks of bundles of parts. ``bundle`` and ``sizes`` are by part, ``chunks`` by bundle."""

    vectors: DataFrame
    blocks: DataFrame
    router: Router
    dim: int
    bundle: np.ndarray
    chunks: np.ndarray
    sizes: np.ndarray


def bundles(sizes: np.ndarray, chunk: int) -> np.ndarray:
    """Bundle of each part: neighbouring parts share one up to ``chunk`` vectors, a larger part has its own."""
    out, number, held = [], 0, 0
    for n in sizes.tolist():
        if held and held + n > chunk:
            number, held = number + 1, 0
        out.append(number)
        held += n
    return np.array(out, np.int64)


def _of(values: np.ndarray, at: Column) -> Column:
    return F.element_at(F.array(*[F.lit(int(v)) for v in values]), (at + 1).cast("int"))


def build_index(rows: DataFrame, parts: int | None = None, sample: int = 8192, chunk: int = 4096, target: float = 0.94, k: int = 20, id_col: str = "vec_id", vector_col: str = "embedding") -> Index:
    """An index of all valid vectors. ``parts`` is the square root of their number by default, at most one for 32 sampled vectors."""
    spark = rows.sparkSession
    valid, n = valid_vectors(rows, id_col, vector_col)
    got = valid.orderBy(F.xxhash64("id"), "id").limit(sample).toArrow()
    x = _matrix(got.column("v")) if got.num_rows else np.zeros((0, 1))
    router = fit_router(x, parts or min(round(n**0.5), max(2, sample // 32)), k, target=target)
    placed = materialise(valid.mapInArrow(_place(spark.sparkContext.broadcast(router)), "part int, id long, v binary"), "vectors")
    counts = {r[0]: r[1] for r in placed.groupBy("part").count().collect()}
    sizes = np.array([counts.get(p, 0) for p in range(router.parts)], np.int64)
    bundle = bundles(sizes, chunk)
    chunks = -(-np.maximum(1, np.bincount(bundle, sizes).astype(np.int64)) // chunk)
    dealt = placed.withColumn("bundle", _of(bundle, F.col("part"))).withColumn("chunk", F.pmod(F.xxhash64("id", F.lit(9)), _of(chunks, F.col("bundle")).cast("long")))
    blocks = dealt.groupBy("bundle", "chunk").applyInArrow(_block, "bundle int, chunk long, ids binary, parts binary, block binary")
    return Index(valid, blocks, router, x.shape[1], bundle, chunks, sizes)


def search(index: Index, queries: DataFrame, k: int = 20, chunk: int = 1024) -> DataFrame:
    """(query_id, rank, vec_id, score). ``queries`` is (id, v)."""
    shared = queries.sparkSession.sparkContext.broadcast((index.router, index.bundle, index.sizes))
    asked = queries.dropDuplicates(["id"])
    many = max(1, -(-asked.count() // chunk))
    routed = asked.mapInArrow(_route(shared, 4 * k), "bundle int, id long, v binary, probed binary").withColumn("deal", F.pmod(F.xxhash64("id", F.lit(7)), F.lit(many)))
    blocks = routed.groupBy("bundle", "deal").applyInArrow(_query_block, "bundle int, q_ids binary, q_block binary, q_many binary, q_parts binary")
    blocks = blocks.withColumn("chunk", F.explode(F.sequence(F.lit(0).cast("long"), _of(index.chunks, F.col("bundle")).cast("long") - 1)))
    found = index.blocks.join(blocks, ["bundle", "chunk"]).drop("bundle", "chunk").mapInArrow(_rerank(index.dim, k), "query_id long, vec_id long, score double")
    best = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op8_ann(spark: SparkSession, sf_dir: str) -> DataFrame:
    index = build_index(table(spark, sf_dir, "embeddings"))
    return search(index, index.vectors.where("id % 20 = 0"))


QUERIES = {"op8_ann": op8_ann}
ORACLES: dict[str, str] = {}
