"""N-gram Jaccard self-join by a MinHash LSH forest with exact verification.

Every distinct shingle set gets a label of MinHash values in each of ``trees`` prefix trees, and sets that share a
prefix are candidates. ``forest_depth`` starts from whole labels and shortens the matched prefix until a pair at the
threshold is met in some tree with the target recall. That depends on threshold, trees and target alone, so it is settled
before the join and only prefixes of that length are kept. Sets that share prefixes fall into candidate groups (connected components
over prefixes). A group of at most ``tile`` sets is verified whole, so that each of its sets travels once however many
prefixes it shares. The sets of larger groups are put in the order of their prefixes and cut into blocks of ``tile``;
two blocks are compared where some prefix is in both. A pair is verified exactly, in one place.

Copies never multiply: documents with one shingle set are one unit from the start. Pairs are verified as products of
0/1 matrices of at most ``tile`` x ``tile`` units; a tile returns a count and a link per unit, never pairs, and
a large group is many tiles in many tasks. Joins on prefixes, groups and nodes spare hubs.

Result, a row per document: ``class_id`` (smallest doc_id linked directly or through others; copies included),
``copy_of`` (smallest doc_id with the same shingle set), ``n_copies`` (documents with that set), ``n_links`` (other
distinct shingle sets at the threshold or above), ``class_key`` (least hash of a set of the class).

Words are lower-case, ASCII punctuation apart. Fewer than five words make one shingle; a text without words (null,
empty, marks only) is a class of its own without copies or links. Null ids: such rows take part; their ids stay null in
the result and their class is that of their set. Rows with one id and different texts are told apart by their set: of
classes with one smallest id, the one with the least key is named by the id, the others (and classes without ids) by
their key. Very long texts are shingled whole. Empty table: no rows. Other columns are not read.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import TokenHasher, materialise, slices, small, table, tidy, unused, words
from .components import connected_components, keyed_join

TREES, DEPTH, TARGET = 32, 10, 0.999


def forest_depth(threshold: float, trees: int, depth: int, target: float) -> int:
    """Longest prefix that meets a pair at the threshold in one of the trees with the target recall."""
    while depth > 1 and 1 - (1 - threshold**depth) ** trees < target:
        depth -= 1
    return depth


def shingles(lists: list[list[str]], hasher: TokenHasher, n: int) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of each list of words."""
    tokens = hasher([w for x in lists for w in x])
    grams = np.zeros(len(tokens), np.uint64)
    for k in range(n):
        grams[: max(0, len(tokens) - k)] = (grams[: max(0, len(tokens) - k)] * np.uint64(0x9E3779B97F4A7C15)) ^ tokens[k:]
    grams ^= grams >> np.uint64(29)
    grams *= np.uint64(0xBF58476D1CE4E5B9)
    grams ^= grams >> np.uint64(32)
    out, at = [], 0
    for x in lists:
        if len(x) >= n:
            out.append(np.unique(grams[at : at + len(x) - n + 1]))
        else:
            out.append(np.array([xxhash.xxh64_intdigest("\x00".join(x))], np.uint64) if x else np.zeros(0, np.uint64))
        at += len(x)
    return out


def _permutations(n: int) -> tuple[np.ndarray, np.ndarray]:
    dice = np.random.default_rng(20)
    return dice.integers(1, 1 << 32, n, dtype=np.uint64) | np.uint64(1), dice.integers(0, 1 << 32, n, dtype=np.uint64)


def signatures(sets: list[np.ndarray], trees: int, depth: int) -> np.ndarray:
    """MinHash values, a row per non-empty set: trees x depth values of 32 bits."""
    mul, add = _permutations(trees * depth)
    mul, add = mul.astype(np.uint32) | np.uint32(1), add.astype(np.uint32)
    flat = np.concatenate(sets)
    low = (flat >> np.uint64(32)).astype(np.uint32) ^ flat.astype(np.uint32)
    sizes = np.array([len(s) for s in sets])
    start = np.cumsum(sizes) - sizes
    out = np.empty((len(sets), trees * depth), np.uint32)
    step = 1 << 16
    for a, b in slices(sizes.tolist(), step):
        x = low[start[a] : start[b - 1] + sizes[b - 1]]
        at = start[a:b] - start[a]
        for k in range(trees * depth):
            h = x * mul[k] + add[k]
            h ^= h >> np.uint32(15)
            h *= np.uint32(0x2C1B3C6D)
            h ^= h >> np.uint32(13)
            out[a:b, k] = np.minimum.reduceat(h, at)
    return out


def _sign(n: int, trees: int, depth: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hasher = TokenHasher()
        for batch in batches:
            texts = batch.column("text")
            for a, b in slices(pc.fill_null(pc.utf8_length(texts), 0).to_pylist(), 1 << 21):
                sets = shingles([words(t) for t in texts.slice(a, b - a).to_pylist()], hasher, n)
                full = [i for i, s in enumerate(sets) if len(s)]
                prefix: list[bytes | None] = [None] * len(sets)
                if full:
                    values = signatures([sets[i] for i in full], trees, depth).reshape(len(full), trees, depth)
                    path = np.zeros((len(full), trees), np.uint64)
                    for k in range(depth):
                        path = (path ^ values[:, :, k]) * np.uint64(0x9E3779B97F4A7C15)
                        path ^= path >> np.uint64(31)
                    for i, p in zip(full, path, strict=True):
                        prefix[i] = p.view(np.int64)
                digest = [(xxhash.xxh3_64_intdigest(s.tobytes()), xxhash.xxh64_intdigest(s.tobytes())) for s in sets]
                signed = lambda xs: pa.array(np.array(xs, np.uint64).view(np.int64))
                yield pa.RecordBatch.from_pydict({"id": batch.column("id").slice(a, b - a), "text_hash": batch.column("text_hash").slice(a, b - a), "h1": signed([x for x, _ in digest]), "h2": signed([y for _, y in digest]), "size": pa.array([len(s) for s in sets], pa.int32()), "prefixes": pa.array(prefix, pa.list_(pa.int64()))})
        tidy()

    return run


def _reshingle(n: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hasher = TokenHasher()
        for batch in batches:
            texts = batch.column("text")
            for a, b in slices(pc.fill_null(pc.utf8_length(texts), 0).to_pylist(), 1 << 21):
                sets = shingles([words(t) for t in texts.slice(a, b - a).to_pylist()], hasher, n)
                signed = lambda xs: pa.array(np.array(xs, np.uint64).view(np.int64))
                yield pa.RecordBatch.from_pydict({"id": batch.column("id").slice(a, b - a), "h1": signed([xxhash.xxh3_64_intdigest(s.tobytes()) for s in sets]), "h2": signed([xxhash.xxh64_intdigest(s.tobytes()) for s in sets]), "shingles": pa.array([s.tobytes() for s in sets], pa.binary())})
        tidy()

    return run


def overlaps(left: list[np.ndarray], right: list[np.ndarray] | None, width: int = 4096) -> np.ndarray:
    """|A & B| for all A of ``left`` and B of ``right`` (``left`` itself if None), by products of 0/1 matrices."""
    sets = left + (right or [])
    code, column = np.unique(np.concatenate(sets), return_inverse=True)
    row = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    if right is None:
        useful = np.bincount(column, minlength=len(code)) > 1
    else:
        useful = (np.bincount(column[row < len(left)], minlength=len(code)) > 0) & (np.bincount(column[row >= len(left)], minlength=len(code)) > 0)
    held = useful[column]
    row, column = row[held], (np.cumsum(useful) - 1)[column[held]]
    order = np.argsort(column, kind="stable")
    row, column = row[order], column[order]
    out = np.zeros((len(left), len(right) if right is not None else len(left)), np.float32)
    edges = np.searchsorted(column, np.arange(0, int(useful.sum()) + width, width))
    for k, (a, b) in enumerate(itertools.pairwise(edges.tolist())):
        part = np.zeros((len(sets), width), np.float32)
        part[row[a:b], column[a:b] - k * width] = 1
        out += part[: len(left)] @ (part if right is None else part[len(left) :]).T
    return out


def _verify(threshold: float):
    def one(units: np.ndarray, sides: np.ndarray, sets: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Units, their number of links here, and a linked unit or themselves."""
        size = np.array([len(s) for s in sets], np.float32)
        if (sides < 2).all():
            first, second = np.flatnonzero(sides == 0), np.flatnonzero(sides == 1)
            if not len(first) or not len(second):
                return units, np.zeros(len(units), np.int64), []
            both = overlaps([sets[i] for i in first], [sets[i] for i in second])
            alike = both >= threshold * (size[first][:, None] + size[second][None, :] - both) - 1e-3
            links = np.zeros(len(units), np.int64)
            links[first], links[second] = alike.sum(1), alike.sum(0)
            pairs = [(units[first[i]], units[second[j]]) for i, j in _spanning(alike, len(first))]
            return units, links, pairs
        both = overlaps(sets, None)
        alike = both >= threshold * (size[:, None] + size[None, :] - both) - 1e-3
        np.fill_diagonal(alike, False)
        return units, alike.sum(1), [(units[i], units[j]) for i, j in _forest(alike)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = pa.Table.from_batches(list(batches))
        if not held.num_rows:
            return
        group = held.column("grp").to_numpy()
        order = np.argsort(group, kind="stable")
        units, sides, data = held.column("unit").to_numpy(), held.column("side").to_numpy(), held.column("shingles").to_pylist()
        for rows in np.split(order, np.flatnonzero(np.diff(group[order])) + 1):
            u, links, pairs = one(units[rows], sides[rows], [np.frombuffer(data[i], np.uint64) for i in rows])
            if len(pairs):
                a, b = zip(*pairs, strict=True)
            else:
                a = b = ()
            yield pa.RecordBatch.from_pydict({"unit": pa.array([*u.tolist(), *map(int, a)], pa.int64()), "n": pa.array([*links.tolist(), *[0] * len(a)], pa.int64()), "other": pa.array([*[None] * len(u), *map(int, b)], pa.int64())})

    return run


def _forest(alike: np.ndarray) -> list[tuple[int, int]]:
    """A spanning forest of the graph of a square matrix."""
    left, out = np.ones(len(alike), bool), []
    for s in range(len(alike)):
        if not left[s]:
            continue
        left[s] = False
        queue = [s]
        while queue:
            x = queue.pop()
            new = np.flatnonzero(alike[x] & left)
            left[new] = False
            out += [(int(x), int(y)) for y in new]
            queue += new.tolist()
    return out


def _spanning(alike: np.ndarray, n: int) -> list[tuple[int, int]]:
    """Spanning forest of a bipartite graph."""
    whole = np.zeros((sum(alike.shape),) * 2, bool)
    whole[:n, n:] = alike
    whole[n:, :n] = alike.T
    return [(min(a, b), max(a, b) - n) for a, b in _forest(whole)]


def jaccard_classes(docs: DataFrame, threshold: float = 0.8, n: int = 5, trees: int = TREES, depth: int = DEPTH, target: float = TARGET, tile: int = 512, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, text_hash, h1, h2, class_id, copy_of, n_copies, n_links, class_key), a row per row of ``docs``."""
    depth = forest_depth(threshold, trees, depth, target)
    d = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    signed = materialise(d.withColumn("text_hash", F.xxhash64("text")).mapInArrow(_sign(n, trees, depth), "id long, text_hash long, h1 long, h2 long, size int, prefixes array<long>"), "signatures")
    by = ["h1", "h2"]
    units = signed.where("size > 0").groupBy(*by).agg(F.min("id").alias("copy_of"), F.count("*").alias("n_copies"), F.first("prefixes").alias("prefixes"))
    units = materialise(units.withColumn("unit", F.monotonically_increasing_id()), "units")

    paths = units.select("unit", F.posexplode("prefixes").alias("tree", "path"))
    found = paths.groupBy("tree", "path").agg(F.count("*").alias("n"), F.min("unit").alias("low"), F.sum(F.xxhash64("unit").cast("decimal(20,0)")).alias("sig")).where("n > 1")
    found = found.groupBy("n", "low", "sig").agg(F.min(F.struct("tree", "path")).alias("k")).select("k.tree", "k.path", "low", "n").persist()
    near = keyed_join(paths, found, ["tree", "path"], trees * units.count()).where("unit <> low").select(F.col("unit").alias("a"), F.col("low").alias("b")).distinct()
    groups = connected_components(near)
    found.unpersist()

    sizes = groups.groupBy("root").agg(F.count("*").alias("members")).persist()
    total = sizes.agg(F.coalesce(F.sum("members"), F.lit(0))).first()[0]
    member = keyed_join(groups, sizes, ["root"], total, "members").select(F.col("node").alias("unit"), "root", "members")
    involved = materialise(member.join(units.select("unit", *by, "copy_of", "prefixes"), "unit"), "involved")
    sizes.unpersist()

    carriers = small(involved.select(F.col("copy_of").alias("carrier")).distinct())
    hosts = d.join(carriers, F.col("id").eqNullSafe(F.col("carrier")), "left_semi")
    sets = hosts.mapInArrow(_reshingle(n), "id long, h1 long, h2 long, shingles binary").dropDuplicates(by).select(*by, "shingles")
    ready = materialise(involved.join(sets, by).select("unit", "root", "members", "shingles", F.when(F.col("members") > tile, F.col("prefixes")).alias("prefixes")), "sets")
    tiles, held = _tiles(ready, tile)
    links = materialise(tiles.groupBy("bundle").applyInArrow(_verify_table(threshold), "unit long, n long, other long"), "verified")
    for df in held:
        df.unpersist()

    linked = links.where("other is null").groupBy("unit").agg(F.sum("n").alias("n_links"))
    classes = connected_components(links.where("other is not null").select(F.col("unit").alias("a"), F.col("other").alias("b")))
    placed = units.drop("prefixes").join(linked, "unit", "left").join(classes.withColumnRenamed("node", "unit"), "unit", "left")
    firsts = _named(materialise(placed.select(*by, "copy_of", "n_copies", F.coalesce("n_links", F.lit(0).cast("long")).alias("n_links"), "root"), "placed"))
    out = signed.select("id", "text_hash", *by, "size").join(firsts, by, "left")
    alone = F.col("size") == 0
    own = {"class_id": F.col("id"), "copy_of": F.col("id"), "n_copies": F.lit(1).cast("long"), "n_links": F.lit(0).cast("long"), "class_key": F.xxhash64("id", "text_hash")}
    return out.select(F.col("id").alias(id_col), "text_hash", *by, *[F.when(alone, x).otherwise(F.col(k)).alias(k) for k, x in own.items()])


def _named(placed: DataFrame) -> DataFrame:
    """Units with the name and key of their class, which is that of ``root``, or their own where that is null."""
    classes = placed.where("root is not null").groupBy("root").agg(F.min("copy_of").alias("least"), F.min("h1").alias("class_key"), F.count("*").alias("n"))
    classes = materialise(classes, "classes")
    single = placed.where("root is null").select("*", F.col("copy_of").alias("least"), F.col("h1").alias("class_key"))
    rest = ["h1", "h2", "copy_of", "n_copies", "n_links", "least", "class_key"]
    every = keyed_join(placed.where("root is not null"), classes, ["root"], placed.count()).select(*rest).unionByName(single.select(*rest))
    taken = classes.select("least", "class_key").unionByName(single.select("least", "class_key")).where("least is not null")
    taken = taken.groupBy("least").agg(F.min("class_key").alias("first"), F.count("*").alias("many")).where("many > 1").drop("many")
    if taken.isEmpty():
        return every.withColumn("class_id", F.coalesce("least", "class_key")).drop("least")
    named = every.join(materialise(taken, "taken"), "least", "left")
    return named.withColumn("class_id", F.when(F.col("first") < F.col("class_key"), F.col("class_key")).otherwise(F.coalesce("least", "class_key"))).drop("least", "first")


def _tiles(ready: DataFrame, tile: int) -> tuple[DataFrame, list[DataFrame]]:
    """(unit, grp, side, bundle, shingles): the units of each tile. Side 2: all pairs; else pairs of side 0 and side 1. Also what is cached.

    A small group is a tile and shares a task with others. Large groups are in the order of their prefixes; a tile is a block or a pair of blocks.
    """
    total = ready.agg(F.count("*"), F.sum(F.octet_length("shingles")), F.count(F.when(F.col("members") > tile, 1))).first()
    bundles = max(8, -(-total[0] // 2048), -(-(total[1] or 0) // (1 << 23)))
    out = ready.where(F.col("members") <= tile).select("unit", F.col("root").alias("grp"), F.lit(2).alias("side"), F.pmod(F.xxhash64("root"), F.lit(bundles)).alias("bundle"), "shingles")
    if not total[2]:
        return out, []
    ranged = ready.where(F.col("members") > tile).withColumn("p0", F.col("prefixes")[0]).withColumn("p1", F.try_element_at("prefixes", F.lit(2))).repartitionByRange("root", "p0", "p1", "unit").sortWithinPartitions("root", "p0", "p1", "unit")
    ranged = first = ranged.select("unit", "prefixes", "shingles", F.spark_partition_id().alias("part"), (F.monotonically_increasing_id() % (1 << 33)).alias("own")).persist()
    before = ranged.groupBy("part").agg(F.count("*").alias("n")).select("part", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    ranged = ranged.join(F.broadcast(before), "part").withColumn("block", F.floor((F.col("before") + F.col("own")) / tile)).drop("part", "own", "before")
    held = ranged.select("block", F.posexplode("prefixes").alias("tree", "path")).distinct().persist()
    pairs = held.withColumnRenamed("block", "a").join(held.withColumnRenamed("block", "b"), ["tree", "path"]).where("a <= b").select("a", "b").distinct()
    member = lambda block, side: F.struct(F.col(block).alias("block"), F.lit(side).alias("side"))
    sides = pairs.select("a", "b", F.explode(F.when(F.col("a") == F.col("b"), F.array(member("a", 2))).otherwise(F.array(member("a", 0), member("b", 1)))).alias("t")).select(F.xxhash64("a", "b").alias("grp"), "t.block", "t.side")
    big = ranged.join(sides, "block").select("unit", "grp", "side", F.col("grp").bitwiseOR(F.lit(-(2**63))).alias("bundle"), "shingles")
    return out.unionByName(big), [first, held]


def _verify_table(threshold: float):
    run = _verify(threshold)

    def of(held: pa.Table) -> pa.Table:
        schema = pa.schema([("unit", pa.int64()), ("n", pa.int64()), ("other", pa.int64())])
        out = pa.Table.from_batches(list(run(iter(held.to_batches()))), schema)
        tidy()
        return out

    return of


def drop_near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **params) -> DataFrame:
    """``docs`` with all columns and one row of each class, the one with the smallest id.

    Rows without an id are kept. Of rows that share id and text one stays. Rows without words are classes of their own.
    """
    known = docs.where(F.col(id_col).isNotNull())
    each = materialise(jaccard_classes(known, id_col=id_col, text_col=text_col, **params).select(F.col(id_col).alias("id"), "text_hash", "h1", "h2", "class_key"), "classes")
    me = F.struct("id", "h1", "h2", "text_hash")
    best = materialise(each.groupBy("class_key").agg(F.min(me).alias("best"), F.count("*").alias("n")).where("n > 1"), "keepers")
    hash_, lost_id, lost_hash = unused(docs.columns, "text_hash", "lost_id", "lost_hash")
    names = [F.col("id").alias(lost_id), F.col("text_hash").alias(lost_hash)]
    lost = small(materialise(keyed_join(each, best, ["class_key"], each.count()).where(me != F.col("best")).select(*names).distinct(), "lost"))
    twice = materialise(each.groupBy("id", "text_hash").agg(F.count("*").alias("n")).where("n > 1").select(*names), "twice")
    marked = known.withColumn(hash_, F.xxhash64(F.col(text_col).cast("string")))
    same = (marked[id_col].cast("long") == F.col(lost_id)) & (marked[hash_] == F.col(lost_hash))
    kept = marked.join(lost, same, "left_anti")
    if not twice.isEmpty():
        twice = small(twice)
        kept = kept.join(twice, same, "left_anti").unionByName(kept.join(twice, same, "left_semi").dropDuplicates([id_col, hash_]))
    return kept.drop(hash_).unionByName(docs.where(F.col(id_col).isNull()))


def op3_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_classes(table(spark, sf_dir, "documents")).select("doc_id", "class_id", "copy_of", "n_copies", "n_links")


QUERIES = {"op3_ngram_join": op3_ngram_join}
ORACLES: dict[str, str] = {}
