"""Graphs over the given tables, and the same graphs as SQL for checks.

``SQL[name]`` defines relations ``v(id, color)`` and ``e(src, dst, weight)`` as common table expressions.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from arcloom import rng
from arcloom.model import PropertyGraph, both_ways
from arcloom.plans.iterate import cut

SEED = 42
#: Account balances are scaled from these bounds, which hold all of them.
LOW, HIGH = -1000.0, 10000.0


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def stored(g: PropertyGraph) -> PropertyGraph:
    """The graph built once, for what reads it more than once."""
    return PropertyGraph(cut(g.vertices), cut(g.edges))


def balance(column: str):
    return (F.col(column) - LOW) / (HIGH - LOW)


def _shared(rows: DataFrame, by: str, node: str) -> DataFrame:
    """Edges between nodes in one group: weight is 1 / shared groups. Groups are orders of a few lines."""
    a, b = rows.select(by, F.col(node).alias("a")), rows.select(by, F.col(node).alias("b"))
    return both_ways(a.join(b, by).where("a < b").groupBy("a", "b").agg((F.lit(1.0) / F.count("*")).alias("weight")), "a", "b")


def copart(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    rows = table(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey").distinct()
    v = table(spark, sf_dir, "part", "p_partkey", "p_size").select(F.col("p_partkey").alias("id"), ((F.col("p_size") - 1) / 49.0).alias("color"))
    return PropertyGraph(v, _shared(rows, "l_orderkey", "l_partkey"))


def cosupp(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    rows = table(spark, sf_dir, "lineitem", "l_orderkey", "l_suppkey").distinct()
    v = table(spark, sf_dir, "supplier", "s_suppkey", "s_acctbal").select(F.col("s_suppkey").alias("id"), balance("s_acctbal").alias("color"))
    return PropertyGraph(v, _shared(rows, "l_orderkey", "l_suppkey"))


def _bipartite(pairs: DataFrame, left: DataFrame, right: DataFrame) -> PropertyGraph:
    """Ids are key * 8 + kind."""
    return PropertyGraph(left.unionByName(right), both_ways(pairs, "a", "b"))


def _side(df: DataFrame, key: str, kind: int, color) -> DataFrame:
    return df.select((F.col(key) * 8 + kind).cast("long").alias("id"), color.alias("color"))


def partsupp(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    rows = table(spark, sf_dir, "lineitem", "l_partkey", "l_suppkey", "l_discount")
    w = F.sum(F.round(F.col("l_discount") * 100)) / (F.count("*") * 10)
    pairs = rows.groupBy((F.col("l_partkey") * 8).alias("a"), (F.col("l_suppkey") * 8 + 1).alias("b")).agg(w.alias("weight"))
    return _bipartite(pairs, _side(table(spark, sf_dir, "part"), "p_partkey", 0, (F.col("p_size") - 1) / 49.0), _side(table(spark, sf_dir, "supplier"), "s_suppkey", 1, balance("s_acctbal")))


def _through_orders(spark: SparkSession, sf_dir: str, key: str) -> DataFrame:
    o = table(spark, sf_dir, "orders", "o_orderkey", "o_custkey")
    li = table(spark, sf_dir, "lineitem", "l_orderkey", key)
    return o.join(li, F.col("o_orderkey") == F.col("l_orderkey")).groupBy((F.col("o_custkey") * 8 + 2).alias("a"), (F.col(key) * 8 + (1 if key == "l_suppkey" else 0)).alias("b")).agg((F.lit(1.0) / F.count("*")).alias("weight"))


def custsupp(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    return _bipartite(_through_orders(spark, sf_dir, "l_suppkey"), _side(table(spark, sf_dir, "customer"), "c_custkey", 2, balance("c_acctbal")), _side(table(spark, sf_dir, "supplier"), "s_suppkey", 1, balance("s_acctbal")))


def custpart(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    return _bipartite(_through_orders(spark, sf_dir, "l_partkey"), _side(table(spark, sf_dir, "customer"), "c_custkey", 2, balance("c_acctbal")), _side(table(spark, sf_dir, "part"), "p_partkey", 0, (F.col("p_size") - 1) / 49.0))


def transitions(spark: SparkSession, sf_dir: str, until: int | None = None) -> DataFrame:
    """(a, b): user of an event and of the next one. Days are windows of their own; the last event of a day meets the
    first of the next active day by way of one row a day."""
    ev = table(spark, sf_dir, "events", "event_id", "ts", "user_id").withColumn("day", F.to_date("ts"))
    ev = ev if until is None else ev.where(F.col("event_id") <= until)
    order = Window.partitionBy("day").orderBy("ts", "event_id")
    firsts = ev.groupBy("day").agg(F.min_by("user_id", F.struct("ts", "event_id")).alias("first"))
    following = firsts.select("day", F.lead("first").over(Window.orderBy("day")).alias("following"))
    own = ev.withColumn("b", F.lead("user_id").over(order))
    return own.join(following, "day").select(F.col("user_id").alias("a"), F.coalesce("b", "following").alias("b")).where("b is not null")


def userseq(spark: SparkSession, sf_dir: str, until: int | None = None) -> PropertyGraph:
    """Users whose events follow each other; ``until`` is the last event that counts."""
    pairs = transitions(spark, sf_dir, until).where("a <> b").groupBy(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).agg((F.lit(1.0) / F.count("*")).alias("weight"))
    ev = table(spark, sf_dir, "events", "event_id", "user_id", "event_type")
    ev = ev if until is None else ev.where(F.col("event_id") <= until)
    v = ev.groupBy(F.col("user_id").alias("id")).agg((F.sum(F.when(F.col("event_type") == "error", 1).otherwise(0)) / F.count("*")).alias("color"))
    return PropertyGraph(v, both_ways(pairs, "a", "b"))


def word_id(word):
    return F.conv(F.substring(F.md5(word.cast("binary")), 1, 13), 16, 10).cast("long")


def words(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Neighbouring words of letters a-z; any other character but a blank or newline takes its token out, and ends no pair."""
    tokens = F.filter(F.split(F.lower("text"), "[ \n]+"), lambda t: t.rlike("^[a-z]+$"))
    pairs = table(spark, sf_dir, "documents", "text").select(tokens.alias("t")).where("size(t) > 1")
    pairs = pairs.select(F.explode(F.arrays_zip(F.slice("t", 1, F.size("t") - 1).alias("a"), F.slice("t", 2, F.size("t") - 1).alias("b"))).alias("p")).select("p.a", "p.b").where("a <> b")
    pairs = pairs.groupBy(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).agg((F.lit(1.0) / F.count("*")).alias("weight"))
    e = cut(both_ways(pairs.select(word_id(F.col("a")).alias("a"), word_id(F.col("b")).alias("b"), "weight"), "a", "b"))  # vertices come from edges
    ids = e.select(F.col("src").alias("id")).distinct()
    return PropertyGraph(ids.select("id", rng.uniform(SEED, "color", "id").alias("color")), e)


def docline(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """A document and the smallest document that holds a line of it (trimmed, lower case, 20 characters or more).

    A line links its documents as a star, so a line that many share gives as many edges as documents. Weight is
    1 / shared lines, colour the labelled quality or a half.
    """
    lines = table(spark, sf_dir, "documents", "doc_id", "text").select("doc_id", F.explode(F.split("text", "\n")).alias("line")).select("doc_id", F.md5(F.lower(F.trim("line")).cast("binary")).alias("h"), F.length(F.trim("line")).alias("n")).where("n >= 20").select("doc_id", "h").distinct()
    least = lines.groupBy("h").agg(F.min("doc_id").alias("a"), F.count("*").alias("n")).where("n > 1")
    pairs = lines.join(least, "h").where("doc_id <> a").groupBy("a", F.col("doc_id").alias("b")).agg((F.lit(1.0) / F.count("*")).alias("weight"))
    e = cut(both_ways(pairs, "a", "b"))
    quality = table(spark, sf_dir, "labels", "doc_id", "quality").groupBy("doc_id").agg(F.max("quality").alias("q"))
    ids = e.select(F.col("src").alias("id")).distinct()
    return PropertyGraph(ids.join(quality, ids["id"] == quality["doc_id"], "left").select("id", F.coalesce(F.col("q").cast("double"), F.lit(0.5)).alias("color")), e)


def pageref(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Pages (page_id * 8) and href targets (hash * 8 + 1)."""
    refs = table(spark, sf_dir, "pages", "page_id", "html").select((F.col("page_id") * 8).alias("a"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("href")).distinct()
    refs = refs.withColumn("b", F.shiftright(word_id(F.col("href")), 4) * 8 + 1)
    n = refs.groupBy("b").agg(F.count("*").alias("n"))
    e = cut(both_ways(refs.select("a", "b").distinct().join(n, "b").select("a", "b", (F.lit(1.0) / F.col("n")).alias("weight")), "a", "b"))
    return PropertyGraph(e.select(F.col("src").alias("id")).distinct().select("id", rng.uniform(SEED, "color", "id").alias("color")), e)


def dialog(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Turns (conv_id * 1024 + turn), linked to the next turn."""
    t = table(spark, sf_dir, "conversations", "conv_id", "turn", "role").select((F.col("conv_id") * 1024 + F.col("turn")).alias("id"), "conv_id", "turn", "role")
    role = F.when(F.col("role") == "user", 0.5).when(F.col("role") == "assistant", 1.0).otherwise(0.0)
    nxt = t.select(F.col("conv_id").alias("c"), (F.col("turn") - 1).alias("t"), F.col("id").alias("b"))
    pairs = t.join(nxt, (F.col("conv_id") == F.col("c")) & (F.col("turn") == F.col("t"))).select(F.col("id").alias("a"), "b", F.lit(1.0).alias("weight"))
    return PropertyGraph(t.select("id", role.alias("color")), both_ways(pairs, "a", "b"))


def geo(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """A forest: region (3), nation (4), customer (2) and supplier (1) keys times 8."""
    nation, customer, supplier = table(spark, sf_dir, "nation"), table(spark, sf_dir, "customer"), table(spark, sf_dir, "supplier")
    key = lambda c, k: (F.col(c).cast("long") * 8 + k)
    pairs = nation.select(key("n_regionkey", 3).alias("a"), key("n_nationkey", 4).alias("b")).unionByName(customer.select(key("c_nationkey", 4).alias("a"), key("c_custkey", 2).alias("b"))).unionByName(supplier.select(key("s_nationkey", 4).alias("a"), key("s_suppkey", 1).alias("b")))
    ids = table(spark, sf_dir, "region").select(key("r_regionkey", 3).alias("id")).unionByName(pairs.select(F.col("b").alias("id")))
    return PropertyGraph(ids.select("id", rng.uniform(SEED, "color", "id").alias("color")), both_ways(pairs.select("a", "b", rng.uniform(SEED, "weight", "a", "b").alias("weight")), "a", "b"))


def knn(spark: SparkSession, sf_dir: str, k: int = 10, most_rows: int = 200_000, block: int = 2048, cells: int = 1 << 22) -> PropertyGraph:
    """Exact cosine neighbours in either direction; quadratic, so tables over ``most_rows`` are refused. A task holds the
    vectors and ``cells`` cosines at a time; there are as many copies of the vectors as tasks at once, if blocks allow."""
    import numpy as np
    import pandas as pd

    rows = table(spark, sf_dir, "embeddings").where("embedding is not null")
    n = rows.count()
    if n > most_rows:
        raise ValueError(f"exact neighbours of {n} vectors are quadratic; use the learned-partition search")
    x = rows.select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    parts = max(1, min(-(-n // block), spark.sparkContext.defaultParallelism))
    chunk = F.pmod(F.xxhash64("vec_id"), F.lit(parts)).cast("int")
    left = x.withColumn("part", chunk)
    right = x.withColumn("own", chunk).withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(parts - 1))))

    def best(key, a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        A, B = (np.stack(t["v"].to_numpy()) for t in (a, b))
        A, B = A / np.linalg.norm(A, axis=1, keepdims=True), B / np.linalg.norm(B, axis=1, keepdims=True)
        ia, ib = a["vec_id"].to_numpy(), b["vec_id"].to_numpy()
        out = []
        for rows in np.array_split(np.arange(len(A)), -(-len(A) * len(B) // cells) or 1):
            s = A[rows] @ B.T
            s[ia[rows, None] == ib[None, :]] = -2
            top = np.argsort(-s, axis=1, kind="stable")[:, :k]
            out.append(pd.DataFrame({"a": np.repeat(ia[rows], top.shape[1]), "b": ib[top.ravel()], "cos": np.take_along_axis(s, top, 1).ravel()}))
        return pd.concat(out)

    found = left.groupBy("part").cogroup(right.groupBy("part")).applyInPandas(best, "a long, b long, cos double").where("cos > -2")
    top = found.withColumn("r", F.row_number().over(Window.partitionBy("a").orderBy(F.desc(F.round("cos", 9)), "b"))).where(F.col("r") <= k)
    e = both_ways(top.groupBy(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).agg(F.least(F.greatest((F.max("cos") + 1) / 2, F.lit(0.0)), F.lit(1.0)).alias("weight")), "a", "b")
    return PropertyGraph(rows.select(F.col("vec_id").alias("id"), (F.col("label") / 9.0).alias("color")), e)


GRAPHS: dict[str, Callable[[SparkSession, str], PropertyGraph]] = {f.__name__: f for f in (copart, cosupp, partsupp, custsupp, custpart, userseq, words, docline, pageref, dialog, geo, knn)}

_BOTH = "e AS (SELECT a AS src, b AS dst, weight FROM pairs UNION ALL SELECT b, a, weight FROM pairs)"
_BAL = "({0} + 1000.0) / 11000.0"
_PART, _SUPP, _CUST = "SELECT p_partkey * 8 AS id, (p_size - 1) / 49.0::DOUBLE AS color FROM part", f"SELECT s_suppkey * 8 + 1, {_BAL.format('s_acctbal')} FROM supplier", f"SELECT c_custkey * 8 + 2, {_BAL.format('c_acctbal')} FROM customer"
_WID = "('0x' || substr(md5({0}), 1, 13))::BIGINT"
_HASHED = f"v AS (SELECT id, {rng.sql_uniform(SEED, 'color', 'id')} AS color FROM (SELECT DISTINCT src AS id FROM e))"


def _co(key: str) -> str:
    return f"o AS (SELECT DISTINCT l_orderkey AS k, {key} AS x FROM lineitem), pairs AS (SELECT p.x AS a, q.x AS b, 1.0::DOUBLE / count(*) AS weight FROM o p JOIN o q ON p.k = q.k AND p.x < q.x GROUP BY ALL), {_BOTH}"


def _cust(key: str, kind: int) -> str:
    return f"pairs AS (SELECT o_custkey * 8 + 2 AS a, {key} * 8 + {kind} AS b, 1.0::DOUBLE / count(*) AS weight FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1, 2), {_BOTH}"


SQL = {
    "copart": _co("l_partkey") + ", v AS (SELECT p_partkey AS id, (p_size - 1) / 49.0::DOUBLE AS color FROM part)",
    "cosupp": _co("l_suppkey") + f", v AS (SELECT s_suppkey AS id, {_BAL.format('s_acctbal')} AS color FROM supplier)",
    "partsupp": f"pairs AS (SELECT l_partkey * 8 AS a, l_suppkey * 8 + 1 AS b, sum(round(l_discount * 100)) / (count(*) * 10) AS weight FROM lineitem GROUP BY 1, 2), {_BOTH}, v AS ({_PART} UNION ALL {_SUPP})",
    "custsupp": _cust("l_suppkey", 1) + f", v(id, color) AS ({_CUST} UNION ALL {_SUPP})",
    "custpart": _cust("l_partkey", 0) + f", v AS ({_PART} UNION ALL {_CUST})",
    "userseq": f"t AS (SELECT user_id AS a, lead(user_id) OVER (ORDER BY ts, event_id) AS b FROM events), pairs AS (SELECT least(a, b) AS a, greatest(a, b) AS b, 1.0::DOUBLE / count(*) AS weight FROM t WHERE a <> b GROUP BY 1, 2), {_BOTH}, v AS (SELECT user_id AS id, sum(CASE WHEN event_type = 'error' THEN 1 ELSE 0 END)::DOUBLE / count(*) AS color FROM events GROUP BY 1)",
    "words": f"l AS (SELECT list_filter(regexp_split_to_array(lower(text), '[ \\n]+'), lambda t: regexp_full_match(t, '[a-z]+')) AS t FROM documents), z AS (SELECT unnest(list_zip(t[1:len(t) - 1], t[2:])) AS p FROM l WHERE len(t) > 1), n AS (SELECT least(p[1], p[2]) AS a, greatest(p[1], p[2]) AS b, 1.0::DOUBLE / count(*) AS weight FROM z WHERE p[1] <> p[2] GROUP BY 1, 2), pairs AS (SELECT {_WID.format('a')} AS a, {_WID.format('b')} AS b, weight FROM n), {_BOTH}, {_HASHED}",
    "docline": f"l AS (SELECT DISTINCT doc_id, h FROM (SELECT doc_id, md5(lower(trim(line, ' '))) AS h, length(trim(line, ' ')) AS n FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents)) WHERE n >= 20), m AS (SELECT h, min(doc_id) AS a FROM l GROUP BY h HAVING count(*) > 1), pairs AS (SELECT m.a, doc_id AS b, 1.0::DOUBLE / count(*) AS weight FROM l JOIN m ON l.h = m.h WHERE doc_id <> m.a GROUP BY 1, 2), {_BOTH}, q AS (SELECT doc_id, max(quality) AS q FROM labels GROUP BY 1), v AS (SELECT id, coalesce(q::DOUBLE, 0.5) AS color FROM (SELECT DISTINCT src AS id FROM e) LEFT JOIN q ON id = doc_id)",
    "pageref": f"r AS (SELECT DISTINCT page_id * 8 AS a, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM pages), r2 AS (SELECT a, ({_WID.format('href')} >> 4) * 8 + 1 AS b FROM r), n AS (SELECT b, count(*) AS n FROM r2 GROUP BY b), pairs AS (SELECT DISTINCT a, r2.b, 1.0::DOUBLE / n AS weight FROM r2 JOIN n ON r2.b = n.b), {_BOTH}, {_HASHED}",
    "dialog": f"t AS (SELECT conv_id * 1024 + turn AS id, conv_id, turn, role FROM conversations), pairs AS (SELECT x.id AS a, y.id AS b, 1.0::DOUBLE AS weight FROM t x JOIN t y ON x.conv_id = y.conv_id AND x.turn + 1 = y.turn), {_BOTH}, v AS (SELECT id, CASE role WHEN 'user' THEN 0.5 WHEN 'assistant' THEN 1.0 ELSE 0.0 END::DOUBLE AS color FROM t)",
    "geo": f"p AS (SELECT n_regionkey::BIGINT * 8 + 3 AS a, n_nationkey::BIGINT * 8 + 4 AS b FROM nation UNION ALL SELECT c_nationkey::BIGINT * 8 + 4, c_custkey * 8 + 2 FROM customer UNION ALL SELECT s_nationkey::BIGINT * 8 + 4, s_suppkey * 8 + 1 FROM supplier), pairs AS (SELECT a, b, {rng.sql_uniform(SEED, 'weight', 'a', 'b')} AS weight FROM p), {_BOTH}, v AS (SELECT id, {rng.sql_uniform(SEED, 'color', 'id')} AS color FROM (SELECT r_regionkey::BIGINT * 8 + 3 AS id FROM region UNION ALL SELECT b FROM p))",
    "knn": f"x AS (SELECT vec_id, embedding::DOUBLE[] AS v FROM embeddings WHERE embedding IS NOT NULL), c AS (SELECT p.vec_id AS a, q.vec_id AS b, list_cosine_similarity(p.v, q.v) AS cos FROM x p JOIN x q ON p.vec_id <> q.vec_id), t AS (SELECT *, row_number() OVER (PARTITION BY a ORDER BY round(cos, 9) DESC, b) AS r FROM c), pairs AS (SELECT least(a, b) AS a, greatest(a, b) AS b, least(greatest((max(cos) + 1) / 2, 0.0), 1.0) AS weight FROM t WHERE r <= 10 GROUP BY 1, 2), {_BOTH}, v AS (SELECT vec_id AS id, label / 9.0::DOUBLE AS color FROM embeddings WHERE embedding IS NOT NULL)",
}


def build_query(name: str):
    """One row an arc, with the colour of its source."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        g = GRAPHS[name](spark, sf_dir)
        return g.edges.join(g.vertices, g.edges["src"] == g.vertices["id"]).select("src", "dst", F.round("weight", 6).alias("weight"), F.round("color", 6).alias("color"))

    return run


def scan_pruned(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two columns, one pushed filter."""
    return table(spark, sf_dir, "lineitem", "l_partkey", "l_quantity").where("l_quantity >= 49").groupBy("l_partkey").agg(F.count("*").alias("n"))


QUERIES = {f"build_{k}": build_query(k) for k in GRAPHS} | {"scan_pruned": scan_pruned}
ORACLES = {f"build_{k}": f"WITH {SQL[k]} SELECT src, dst, round(weight, 6) AS weight, round(color, 6) AS color FROM e JOIN v ON src = id" for k in GRAPHS} | {"scan_pruned": "SELECT l_partkey, count(*) AS n FROM lineitem WHERE l_quantity >= 49 GROUP BY 1"}
