"""Layouts of a graph: linked list, packed adjacency, and compressed rows in blocks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from arcloom.model import PropertyGraph
from arcloom.plans.iterate import cut, release
from arcloom.sources.ingest import GRAPHS, SQL, stored


def adjacency(g: PropertyGraph) -> DataFrame:
    """(id, color, nbrs): sorted neighbours and weights in one array a vertex."""
    packed = g.edges.groupBy("src").agg(F.sort_array(F.collect_list(F.struct(F.col("dst").alias("nbr"), "weight"))).alias("nbrs"))
    empty = F.array().cast("array<struct<nbr:bigint,weight:double>>")
    return g.vertices.join(packed, g.vertices["id"] == packed["src"], "left").select("id", "color", F.coalesce("nbrs", empty).alias("nbrs"))


def from_adjacency(packed: DataFrame) -> DataFrame:
    return packed.select(F.col("id").alias("src"), F.explode("nbrs").alias("n")).select("src", F.col("n.nbr").alias("dst"), "n.weight")


def linked_list(g: PropertyGraph) -> tuple[DataFrame, DataFrame]:
    """heads (id, color, head) and nodes (node, nbr, weight, next). Nodes are numbered by the hash of their arc."""
    order = Window.partitionBy("src").orderBy("dst")
    name = F.xxhash64("src", "dst")
    nodes = g.edges.select("src", "dst", "weight", name.alias("node")).withColumn("next", F.lead("node").over(order)).withColumn("pos", F.row_number().over(order))
    first = nodes.where("pos = 1").select(F.col("src").alias("id"), F.col("node").alias("head"))
    return g.vertices.join(first, "id", "left").select("id", "color", "head"), nodes.select("node", F.col("dst").alias("nbr"), "weight", "next")


def from_linked_list(heads: DataFrame, nodes: DataFrame) -> DataFrame:
    """Arcs by following pointers: every node jumps to what its predecessor points back to, so a list of n nodes takes about log2(n) joins."""
    nodes = cut(nodes)
    before = nodes.where("next is not null").select(F.col("next").alias("node"), F.col("node").alias("p"))
    state = cut(nodes.select("node").join(before, "node", "left").select("node", F.coalesce("p", "node").alias("up")))
    for _ in range(64):
        new = cut(state.join(state.select(F.col("node").alias("up"), F.col("up").alias("far")), "up").select("node", F.col("far").alias("up"), (F.col("far") != F.col("up")).alias("moved")))
        release(state)
        state = new
        if new.where("moved").isEmpty():
            break
    first = heads.where("head is not null").select(F.col("id").alias("src"), F.col("head").alias("up"))
    return nodes.join(state.select("node", "up"), "node").join(first, "up").select("src", F.col("nbr").alias("dst"), "weight")


def csr(g: PropertyGraph, block: int = 4096) -> DataFrame:
    """(block, lo, hi, offsets, targets, weights, colors), a row a range of ids; ids are 0..n-1.

    offsets has one entry more than vertices: a vertex without arcs repeats the entry after it.
    """
    rows = adjacency(g).withColumn("block", F.floor(F.col("id") / block))
    by = rows.groupBy("block").agg(F.sort_array(F.collect_list(F.struct("id", "color", "nbrs"))).alias("r"))
    flat = F.flatten(F.transform("r", lambda x: x["nbrs"]))
    offsets = F.aggregate("r", F.array(F.lit(0).cast("long")), lambda acc, x: F.concat(acc, F.array(F.element_at(acc, -1) + F.size(x["nbrs"]))))
    return by.select("block", F.col("r")[0]["id"].alias("lo"), (F.element_at("r", -1)["id"] + 1).alias("hi"), offsets.alias("offsets"), F.transform(flat, lambda n: n["nbr"]).alias("targets"), F.transform(flat, lambda n: n["weight"]).alias("weights"), F.transform("r", lambda x: x["color"]).alias("colors"))


def from_csr(blocks: DataFrame) -> DataFrame:
    v = blocks.select("lo", "offsets", "targets", "weights", F.explode(F.sequence(F.lit(0), F.size("offsets") - 2)).alias("i"))
    begin, end = F.element_at("offsets", F.col("i") + 1), F.element_at("offsets", F.col("i") + 2)
    part = lambda c: F.slice(c, (begin + 1).cast("int"), (end - begin).cast("int"))
    return v.select((F.col("lo") + F.col("i")).alias("src"), F.explode(F.arrays_zip(part("targets").alias("dst"), part("weights").alias("weight"))).alias("a")).select("src", "a.dst", "a.weight")


def layouts(g: PropertyGraph, block: int = 64) -> dict:
    """A graph of ids 0..n-1 in every layout, each stored."""
    heads, nodes = linked_list(g)
    return {"arc_rows": cut(g.edges), "packed": cut(adjacency(g)), "csr": cut(csr(g, block).withColumn("size", F.lit(block))), "linked_list": (cut(heads), cut(nodes))}


def leaving(layout: str, data, front: DataFrame) -> DataFrame:
    """(src, dst) of the arcs that leave ``front`` (id), read from a layout as it is stored: a scan, lists, slices of blocks, or pointers followed one by one."""
    if layout == "arc_rows":
        return data.join(front.withColumnRenamed("id", "src"), "src", "left_semi").select("src", "dst")
    if layout == "packed":
        return data.join(front, "id", "left_semi").select(F.col("id").alias("src"), F.explode("nbrs.nbr").alias("dst"))
    if layout == "csr":
        at = data.join(front.withColumn("v", F.col("id")), (F.col("v") >= F.col("lo")) & (F.col("v") < F.col("hi")) & (F.floor(F.col("v") / F.col("size")) == F.col("block")))
        begin, end = (F.element_at("offsets", (F.col("v") - F.col("lo") + k).cast("int")) for k in (1, 2))
        return at.select(F.col("v").alias("src"), F.explode(F.slice("targets", (begin + 1).cast("int"), (end - begin).cast("int"))).alias("dst"))
    heads, nodes = data
    at, out = cut(heads.join(front, "id", "left_semi").where("head is not null").select(F.col("id").alias("src"), F.col("head").alias("node"))), None
    while not at.isEmpty():
        here = cut(at.join(nodes, "node").select("src", "nbr", "next"))
        arcs = here.select("src", F.col("nbr").alias("dst"))
        out = arcs if out is None else out.unionByName(arcs)
        at = here.where("next is not null").select("src", F.col("next").alias("node"))
    return out if out is not None else at.select("src", F.col("node").alias("dst"))


def levels_on(layout: str, data, spark: SparkSession, source: int) -> DataFrame:
    """(id, level): the search kernel's breadth-first levels on a layout."""
    front = cut(spark.createDataFrame([(source,)], "id long"))
    out, level = front.withColumn("level", F.lit(0)), 0
    while True:
        level += 1
        front = cut(leaving(layout, data, front).select(F.col("dst").alias("id")).distinct().join(out.select("id"), "id", "left_anti"))
        if front.isEmpty():
            return out
        out = out.unionByName(front.withColumn("level", F.lit(level)))


def closed_on(layout: str, data, ids: DataFrame) -> DataFrame:
    """(closed): arcs among the neighbours of the given vertices, the metric kernel's count, on a layout."""
    near = cut(leaving(layout, data, ids))
    around = leaving(layout, data, near.select(F.col("dst").alias("id")).distinct())
    two = near.join(around.select(F.col("src").alias("dst"), F.col("dst").alias("w")), "dst")
    return two.join(near.select("src", F.col("dst").alias("w")), ["src", "w"], "left_semi").agg(F.count("*").alias("closed"))


def footprint(g: PropertyGraph) -> DataFrame:
    """(layout, bytes) with 8 bytes a number: a list pays a pointer an arc, the matrix a cell a pair."""
    n, a = g.vertices.agg(F.count("*").alias("n")), g.edges.agg(F.count("*").alias("a"))
    sizes = {"linked_list": "16 * n + 24 * a", "csr": "8 * n + 8 * (n + 1) + 16 * a", "arc_rows": "16 * n + 24 * a", "matrix": "8 * n + 8 * n * n"}
    rows = F.array(*[F.struct(F.lit(k).alias("layout"), F.expr(e).alias("bytes")) for k, e in sizes.items()])
    return n.crossJoin(a).select(F.explode(rows).alias("r")).select("r.*")


def repr_equivalence(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Arcs that each layout gives back, and the sum of their weights."""
    from arcloom.model import densify

    g, _ = densify(GRAPHS["userseq"](spark, sf_dir))
    g = PropertyGraph(cut(g.vertices), cut(g.edges))
    made = {"arc_rows": g.edges, "packed": from_adjacency(adjacency(g)), "csr": from_csr(csr(g, 64)), "linked_list": from_linked_list(*linked_list(g))}
    out = None
    for name, e in made.items():
        one = e.agg(F.lit(name).alias("layout"), F.count("*").alias("arcs"), F.round(F.sum("weight"), 6).alias("weight"), F.sum(F.col("src") * F.col("dst")).alias("mark"))
        out = one if out is None else out.unionByName(one)
    return out


def _on_layouts(name: str, kernel, most: tuple[str, ...] = ("arc_rows", "packed", "csr", "linked_list")):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        from arcloom.model import densify

        g, _ = densify(stored(GRAPHS[name](spark, sf_dir)))
        g, out = stored(g), None
        for layout, data in layouts(g).items():
            if layout in most:
                one = kernel(layout, data, g).withColumn("layout", F.lit(layout))
                out = one if out is None else out.unionByName(one)
        return out

    return run


QUERIES = {
    "repr_bfs_layouts": _on_layouts("dialog", lambda layout, data, g: levels_on(layout, data, g.spark, 0).groupBy("level").agg(F.count("*").alias("n"))),
    "repr_cc_layouts": _on_layouts("userseq", lambda layout, data, g: closed_on(layout, data, g.vertices.where("id < 5").select("id")), ("arc_rows", "packed", "csr")),
    "repr_equivalence": repr_equivalence, "measure_footprint": lambda spark, sf_dir: footprint(GRAPHS["copart"](spark, sf_dir))}
_DENSE = "m AS (SELECT id, row_number() OVER (ORDER BY id) - 1 AS k FROM v), f AS (SELECT count(*) AS arcs, round(sum(weight), 6) AS weight, sum(a.k * b.k)::BIGINT AS mark FROM e JOIN m a ON a.id = src JOIN m b ON b.id = dst)"
ORACLES = {
    "repr_bfs_layouts": f"WITH RECURSIVE {SQL['dialog']}, b(id, level) USING KEY (id) AS (SELECT min(id), 0 FROM v UNION SELECT dst, min(b.level + 1) FROM b JOIN e ON src = b.id LEFT JOIN recurring.b AS r ON r.id = dst WHERE r.level IS NULL GROUP BY 1) SELECT layout, level::INTEGER AS level, count(*) AS n FROM b, (SELECT unnest(['arc_rows', 'packed', 'csr', 'linked_list']) AS layout) GROUP BY 1, 2",
    "repr_cc_layouts": f"WITH {SQL['userseq']}, five AS (SELECT id FROM v ORDER BY id LIMIT 5) SELECT layout, count(*) AS closed FROM e a JOIN e b ON b.src = a.dst JOIN e c ON c.src = a.src AND c.dst = b.dst, (SELECT unnest(['arc_rows', 'packed', 'csr']) AS layout) WHERE a.src IN (SELECT id FROM five) GROUP BY 1",
    "repr_equivalence": f"WITH {SQL['userseq']}, {_DENSE} SELECT layout, arcs, weight, mark FROM f, (SELECT unnest(['arc_rows', 'packed', 'csr', 'linked_list']) AS layout)",
    "measure_footprint": f"WITH {SQL['copart']}, n AS (SELECT count(*) AS n FROM v), a AS (SELECT count(*) AS a FROM e) SELECT unnest(['linked_list', 'csr', 'arc_rows', 'matrix']) AS layout, unnest([16 * n + 24 * a, 8 * n + 8 * (n + 1) + 16 * a, 16 * n + 24 * a, 8 * n + 8 * n * n]) AS bytes FROM n, a",
}
