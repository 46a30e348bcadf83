"""Scalar, array, map, JSON and user-defined functions, and the SQL surface."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from arcloom import rng
from arcloom.functions.scalar import binary_entropy
from arcloom.model import PropertyGraph
from arcloom.operators.metrics import degrees
from arcloom.operators.represent import adjacency, csr
from arcloom.sources.ingest import GRAPHS, SEED, SQL, table


def register(spark: SparkSession, g: PropertyGraph, prefix: str) -> None:
    """Views <prefix>_vertices, <prefix>_edges and <prefix>_packed, and the functions binary_entropy and neighbors."""
    g.vertices.createOrReplaceTempView(f"{prefix}_vertices")
    g.edges.createOrReplaceTempView(f"{prefix}_edges")
    adjacency(g).createOrReplaceTempView(f"{prefix}_packed")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION binary_entropy(p DOUBLE) RETURNS DOUBLE RETURN CASE WHEN p <= 0 OR p >= 1 THEN 0.0D ELSE -p * log2(p) - (1 - p) * log2(1 - p) END")
    spark.udtf.register("neighbors", Neighbors)


@F.udtf(returnType="nbr bigint, weight double")
class Neighbors:
    """Neighbours in a packed list."""

    def eval(self, nbrs: list):
        for n in nbrs or []:
            yield n["nbr"], n["weight"]


@F.pandas_udf(T.DoubleType())
def cosine_udf(a: pd.Series, b: pd.Series) -> pd.Series:
    import numpy as np

    x, y = np.stack(a.to_numpy()).astype(float), np.stack(b.to_numpy()).astype(float)
    return pd.Series((x * y).sum(1) / np.sqrt((x * x).sum(1) * (y * y).sum(1)))


@F.pandas_udf(T.DoubleType())
def tail_udaf(degree: pd.Series) -> float:
    import numpy as np

    d = degree[degree >= 4].to_numpy(dtype=float)
    return float(1 + len(d) / np.log(d / 3.5).sum()) if len(d) else 0.0


@F.udtf(returnType=T.StructType([T.StructField("src", T.LongType()), T.StructField("dst", T.LongType()), T.StructField("weight", T.DoubleType())]))
class CsrExpand:
    """Arcs of a compressed block."""

    def eval(self, lo: int, offsets: list, targets: list, weights: list):
        for i in range(len(offsets) - 1):
            for k in range(offsets[i], offsets[i + 1]):
                yield lo + i, targets[k], weights[k]


def cosine(a, b):
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v)
    return dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))


def _next_vectors(spark, sf_dir):
    """Each vector beside the one whose id is one more."""
    e = table(spark, sf_dir, "embeddings", "vec_id", "embedding")
    return e.join(e.select((F.col("vec_id") - 1).alias("vec_id"), F.col("embedding").alias("other")), "vec_id")


def fn_math_entropy(spark, sf_dir):
    return GRAPHS["partsupp"](spark, sf_dir).edges.where("src < dst").select("src", "dst", F.round(binary_entropy(F.col("weight")), 6).alias("h"), F.round(F.sqrt("weight"), 6).alias("root"), F.pmod(F.col("src") - F.col("dst"), F.lit(7)).alias("m"))


def fn_hash_rank(spark, sf_dir):
    return table(spark, sf_dir, "part", "p_partkey").select("p_partkey", rng.bits(SEED, "rank", "p_partkey").alias("r"))


def fn_tokens(spark, sf_dir):
    return table(spark, sf_dir, "documents", "doc_id", "text", "lang", "source").select("doc_id", F.size(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0))).cast("long").alias("words"), F.length("text").cast("long").alias("chars"), F.translate(F.substring("text", 1, 5), "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ").alias("head"), F.concat_ws("-", "lang", "source").alias("tag"), F.levenshtein("lang", "source").cast("long").alias("d"))


def fn_hrefs(spark, sf_dir):
    return table(spark, sf_dir, "pages", "page_id", "url", "html").select("page_id", F.size(F.array_distinct(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1)))).cast("long").alias("hrefs"), F.regexp_extract("url", "https?://([^/]*)", 1).alias("host"))


def fn_event_buckets(spark, sf_dir):
    ev = table(spark, sf_dir, "events", "ts", "event_type")
    return ev.groupBy(F.date_format(F.date_trunc("month", "ts"), "yyyy-MM-dd").alias("month"), "event_type").agg(F.count("*").alias("n"), F.max(F.unix_micros(F.col("ts").cast("timestamp"))).alias("last"), F.max(F.datediff("ts", F.lit("2020-01-01"))).cast("long").alias("days"))


def fn_adjacency_arrays(spark, sf_dir):
    a = adjacency(GRAPHS["userseq"](spark, sf_dir))
    return a.select("id", F.size(F.filter("nbrs", lambda n: n["weight"] < 0.5)).cast("long").alias("light"), F.round(F.aggregate("nbrs", F.lit(0.0), lambda s, n: s + n["weight"]), 6).alias("total"), F.coalesce(F.array_max(F.transform("nbrs", lambda n: n["nbr"])), F.lit(-1)).alias("last"))


def fn_csr_slice(spark, sf_dir):
    """Degrees from consecutive offsets of compressed blocks."""
    b = csr(GRAPHS["cosupp"](spark, sf_dir), 32)
    return b.select("lo", "colors", F.posexplode(F.zip_with(F.slice("offsets", 2, F.size("offsets") - 1), F.slice("offsets", 1, F.size("offsets") - 1), lambda x, y: x - y)).alias("i", "degree"), "block").select("block", F.col("i").cast("long").alias("i"), "degree")


def fn_cosine(spark, sf_dir):
    return _next_vectors(spark, sf_dir).select("vec_id", F.round(cosine(F.col("embedding"), F.col("other")), 6).alias("cos"))


def udf_cosine(spark, sf_dir):
    return _next_vectors(spark, sf_dir).select("vec_id", F.round(cosine_udf("embedding", "other"), 6).alias("cos"))


def fn_neighbor_map(spark, sf_dir):
    m = GRAPHS["cosupp"](spark, sf_dir).edges.groupBy("src").agg(F.map_from_entries(F.collect_list(F.struct("dst", "weight"))).alias("m"))
    return m.select("src", F.size(F.map_keys("m")).cast("long").alias("n"), F.round(F.aggregate(F.map_values(F.transform_values("m", lambda k, v: v * 2)), F.lit(0.0), lambda s, v: s + v), 6).alias("doubled"), F.round(F.coalesce(F.element_at("m", F.lit(1).cast("long")), F.lit(0.0)), 6).alias("to_one"))


def fn_struct_min(spark, sf_dir):
    low = F.min(F.struct("weight", "dst"))
    return GRAPHS["copart"](spark, sf_dir).edges.groupBy("src").agg(low.alias("s")).select("src", "s.dst", F.round("s.weight", 6).alias("weight"))


def fn_props_json(spark, sf_dir):
    ev = table(spark, sf_dir, "events", "event_type", "props")
    return ev.select("event_type", F.from_json("props", "k INT")["k"].alias("k"), F.get_json_object("props", "$.k").cast("int").alias("k2")).groupBy("event_type").agg(F.sum("k").alias("k"), F.sum("k2").alias("k2"), F.count("*").alias("n"))


def fn_null_degree(spark, sf_dir):
    d = degrees(GRAPHS["userseq"](spark, sf_dir))
    return d.select("id", F.round(F.coalesce(F.lit(1.0) / F.nullif(F.col("degree"), F.lit(0)), F.lit(-1.0)), 6).alias("inverse"))


def udaf_tail(spark, sf_dir):
    """The exponent of the heavy tail by kind of vertex."""
    d = degrees(GRAPHS["custsupp"](spark, sf_dir)).select((F.col("id") % 8).cast("int").alias("kind"), "degree")
    return d.groupBy("kind").agg(F.round(tail_udaf("degree"), 6).alias("exponent"))


def udtf_csr_expand(spark, sf_dir):
    spark.udtf.register("csr_expand", CsrExpand)
    csr(GRAPHS["cosupp"](spark, sf_dir), 32).createOrReplaceTempView("csr_blocks")
    return spark.sql("SELECT x.src, x.dst, round(x.weight, 6) AS weight FROM csr_blocks b, LATERAL csr_expand(b.lo, b.offsets, b.targets, b.weights) x")


def udtf_neighbors(spark, sf_dir):
    """Neighbours of a vertex through the SQL surface, and the entropy of their weights."""
    register(spark, GRAPHS["cosupp"](spark, sf_dir), "u")
    return spark.sql("SELECT p.id, n.nbr, round(binary_entropy(n.weight), 6) AS h FROM u_packed p, LATERAL neighbors(p.nbrs) n")


def sql_scalar_sub(spark, sf_dir):
    register(spark, GRAPHS["copart"](spark, sf_dir), "g")
    return spark.sql("SELECT id FROM g_vertices v WHERE color > (SELECT avg(color) FROM g_vertices) AND EXISTS (SELECT 1 FROM g_edges e WHERE e.src = v.id AND e.weight < 0.5)")


def sql_neighbors(spark, sf_dir):
    register(spark, GRAPHS["geo"](spark, sf_dir), "g")
    return spark.sql("SELECT v.id, n.dst, round(n.weight, 6) AS weight FROM g_vertices v JOIN LATERAL (SELECT dst, weight FROM g_edges e WHERE e.src = v.id) n WHERE v.id % 8 = 3")


def sql_recursive_levels(spark, sf_dir):
    register(spark, GRAPHS["geo"](spark, sf_dir), "g")
    return spark.sql("WITH RECURSIVE t(id, level) AS (SELECT id, 0 FROM g_vertices WHERE id % 8 = 3 UNION ALL SELECT e.dst, t.level + 1 FROM t JOIN g_edges e ON e.src = t.id WHERE CASE t.id % 8 WHEN 3 THEN e.dst % 8 = 4 WHEN 4 THEN e.dst % 8 IN (1, 2) ELSE false END) SELECT level, count(*) AS n FROM t GROUP BY level")


NAMES = "fn_math_entropy fn_hash_rank fn_tokens fn_hrefs fn_event_buckets fn_adjacency_arrays fn_csr_slice fn_cosine udf_cosine fn_neighbor_map fn_struct_min fn_props_json fn_null_degree udaf_tail udtf_csr_expand udtf_neighbors sql_scalar_sub sql_neighbors sql_recursive_levels".split()
QUERIES = {n: globals()[n] for n in NAMES}
_COS = "SELECT a.vec_id, round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) AS cos FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1"
ORACLES = {
    "fn_math_entropy": f"WITH {SQL['partsupp']} SELECT src, dst, round(CASE WHEN weight <= 0 OR weight >= 1 THEN 0.0 ELSE -weight * log2(weight) - (1 - weight) * log2(1 - weight) END, 6) AS h, round(sqrt(weight), 6) AS root, ((src - dst) % 7 + 7) % 7 AS m FROM e WHERE src < dst",
    "fn_hash_rank": f"SELECT p_partkey, {rng.sql_bits(SEED, 'rank', 'p_partkey')} AS r FROM part",
    "fn_tokens": "SELECT doc_id, len(regexp_extract_all(lower(text), '[a-z]+')) AS words, length(text) AS chars, translate(text[1:5], 'abcdefghijklmnopqrstuvwxyz', 'ABCDEFGHIJKLMNOPQRSTUVWXYZ') AS head, lang || '-' || source AS tag, levenshtein(lang, source) AS d FROM documents",
    "fn_hrefs": "SELECT page_id, len(list_distinct(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1))) AS hrefs, regexp_extract(url, 'https?://([^/]*)', 1) AS host FROM pages",
    "fn_event_buckets": "SELECT strftime(date_trunc('month', ts), '%Y-%m-%d') AS month, event_type, count(*) AS n, max(epoch_us(ts)) AS last, max(datediff('day', DATE '2020-01-01', ts::DATE)) AS days FROM events GROUP BY 1, 2",
    "fn_adjacency_arrays": f"WITH {SQL['userseq']} SELECT id, count(*) FILTER (weight < 0.5) AS light, round(coalesce(sum(weight), 0.0), 6) AS total, coalesce(max(dst), -1) AS last FROM v LEFT JOIN e ON id = src GROUP BY 1",
    "fn_csr_slice": f"WITH {SQL['cosupp']}, d AS (SELECT id, count(dst) AS degree FROM v LEFT JOIN e ON id = src GROUP BY 1) SELECT id // 32 AS block, row_number() OVER (PARTITION BY id // 32 ORDER BY id) - 1 AS i, degree FROM d",
    "fn_cosine": _COS,
    "udf_cosine": _COS,
    "fn_neighbor_map": f"WITH {SQL['cosupp']} SELECT src, count(*) AS n, round(2 * sum(weight), 6) AS doubled, round(coalesce(sum(weight) FILTER (dst = 1), 0.0), 6) AS to_one FROM e GROUP BY 1",
    "fn_struct_min": f"WITH {SQL['copart']} SELECT src, dst, round(weight, 6) AS weight FROM e QUALIFY row_number() OVER (PARTITION BY src ORDER BY weight, dst) = 1",
    "fn_props_json": "SELECT event_type, sum((props::JSON->>'k')::INT)::BIGINT AS k, sum((props::JSON->>'k')::INT)::BIGINT AS k2, count(*) AS n FROM events GROUP BY 1",
    "fn_null_degree": f"WITH {SQL['userseq']} SELECT id, round(coalesce(1.0 / nullif(count(dst), 0), -1.0)::DOUBLE, 6) AS inverse FROM v LEFT JOIN e ON id = src GROUP BY 1",
    "udaf_tail": f"WITH {SQL['custsupp']}, d AS (SELECT id % 8 AS kind, count(dst) AS degree FROM v LEFT JOIN e ON id = src GROUP BY id) SELECT kind::INTEGER AS kind, round(1 + count(*) FILTER (degree >= 4) / sum(ln(degree / 3.5)) FILTER (degree >= 4), 6) AS exponent FROM d GROUP BY 1",
    "udtf_csr_expand": f"WITH {SQL['cosupp']} SELECT src, dst, round(weight, 6) AS weight FROM e",
    "udtf_neighbors": f"WITH {SQL['cosupp']} SELECT src AS id, dst AS nbr, round(CASE WHEN weight <= 0 OR weight >= 1 THEN 0.0 ELSE -weight * log2(weight) - (1 - weight) * log2(1 - weight) END, 6) AS h FROM e",
    "sql_scalar_sub": f"WITH {SQL['copart']} SELECT id FROM v WHERE color > (SELECT avg(color) FROM v) AND id IN (SELECT src FROM e WHERE weight < 0.5)",
    "sql_neighbors": f"WITH {SQL['geo']} SELECT src AS id, dst, round(weight, 6) AS weight FROM e WHERE src % 8 = 3",
    "sql_recursive_levels": "SELECT 0::INTEGER AS level, count(*) AS n FROM region UNION ALL SELECT 1, count(*) FROM nation UNION ALL SELECT 2, (SELECT count(*) FROM customer) + (SELECT count(*) FROM supplier)",
}
