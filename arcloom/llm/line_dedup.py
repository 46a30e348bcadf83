"""Line deduplication that returns keep bitmaps instead of text. DataFrame functions only.

The occurrences of all lines are range-partitioned by the hash of their key and sorted by document and position, so that
the occurrences of a key come in one run with the first one ahead; a window streams over the runs and marks what comes
in a later document. There is one range exchange, and no join back to the lines. A key that holds more than
one in 4096 of all lines would make its partition large: such keys (at most 4096, found by a frequent-items sketch of all
lines) have their first document summed up before any exchange and broadcast, and their lines stay where they are.
The result has one row per document that loses lines: its bitmap, 64 positions a word, words without a dropped line
left out.

Null or empty text: one empty line, never dropped. Null ids count as the largest id, and all as one document.
Rows that repeat an id are one document; each row gets the bitmap of its own text. Very long texts are walked line by
line, their bitmaps word by word. Empty table: no rows. Other columns are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import LOWER, SPACES, UPPER, materialise, table

LAST = 2**63 - 1
#: A key that holds one in so many of all lines is hot; there are no more hot keys than that.
HOT_SHARE = 4096


def line_key(line: Column) -> Column:
    return F.translate(F.btrim(line, F.lit(SPACES)), UPPER, LOWER)


def _lines(text: Column) -> Column:
    return F.split(F.coalesce(text, F.lit("")), "\n", -1)


def line_bitmaps(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_chars: int = 10, min_docs: int = 2, hot_share: int = HOT_SHARE) -> DataFrame:
    """(doc, text_hash, n_dropped, dropped map<word, bits>) for the documents that lose lines.

    ``doc`` is the id with null as the largest long; ``text_hash`` is xxhash64 of the text.
    """
    if min_docs != 2:
        raise ValueError("a key is repeated when two documents hold it; other counts are not defined here")
    rows = docs.select(F.coalesce(F.col(id_col).cast("long"), F.lit(LAST)).alias("doc"), F.xxhash64(F.col(text_col)).alias("text_hash"), F.posexplode(_lines(F.col(text_col))).alias("pos", "line"))
    rows = rows.select("doc", "text_hash", "pos", line_key(F.col("line")).alias("key")).where(F.char_length("key") >= min_chars)
    rows = rows.select(F.xxhash64("key").alias("h1"), F.xxhash64(F.lit(1), "key").alias("h2"), "doc", "pos", "text_hash")
    rows = materialise(rows, "lines")  # 40 bytes a line; the range partitioning samples its input, which must not scan the texts again
    hot = hot_firsts(rows, hot_share)
    by_run = Window.partitionBy("h1", "h2").orderBy("doc", "pos").rowsBetween(Window.unboundedPreceding, 0)
    cold = rows if hot is None else rows.join(F.broadcast(hot), ["h1", "h2"], "left_anti")
    late = cold.repartitionByRange("h1", "h2").withColumn("first", F.first("doc").over(by_run)).where("doc > first").drop("first")
    if hot is not None:
        late = late.unionByName(rows.join(F.broadcast(hot), ["h1", "h2"]).where("doc > first").drop("first"))
    bits = late.groupBy("doc", "text_hash", F.expr("pos div 64").cast("int").alias("word")).agg(F.expr("bit_or(shiftleft(1L, pos % 64))").alias("bits"))
    return bits.groupBy("doc", "text_hash").agg(F.sum(F.bit_count("bits")).cast("long").alias("n_dropped"), F.map_from_entries(F.sort_array(F.collect_list(F.struct("word", "bits")))).alias("dropped"))


def hot_firsts(rows: DataFrame, share: int = HOT_SHARE) -> DataFrame | None:
    """(h1, h2, first) of the keys that hold one in ``share`` of all lines, or more, and 1024 lines at least; None if there is none."""
    least = max(1024, rows.count() // share)
    top = rows.agg(F.expr(f"approx_top_k(h1, {share}, {16 * share})").alias("top")).first()["top"] or []
    found = [F.lit(x["item"]) for x in top if x["count"] >= least]
    if not found:
        return None
    names = rows.sparkSession.range(1).select(F.explode(F.array(*found)).alias("h1"))
    return materialise(rows.join(F.broadcast(names), "h1").groupBy("h1", "h2").agg(F.min("doc").alias("first"), F.count("*").alias("n")).where(F.col("n") >= least).drop("n"), "hot-lines")


def _dense(dropped: Column) -> Column:
    """All words of a bitmap, those left out as zero."""
    e = F.map_entries(dropped)
    before = lambda i: F.coalesce(F.get(e, i - 1)["key"], F.lit(-1))
    return F.flatten(F.transform(e, lambda x, i: F.concat(F.array_repeat(F.lit(0).cast("long"), x["key"] - before(i) - 1), F.array(x["value"]))))


def apply_bitmaps(docs: DataFrame, bitmaps: DataFrame, id_col: str = "doc_id", text_col: str = "text", out: str = "kept_text") -> DataFrame:
    """Documents with their kept text; lines come back joined by a newline."""
    d = docs.select(F.col(id_col).alias("_id"), F.coalesce(F.col(id_col).cast("long"), F.lit(LAST)).alias("doc"), F.xxhash64(F.col(text_col)).alias("text_hash"), F.col(text_col).alias("_text"))
    lines, one = _lines(F.col("_text")), F.array(*[F.lit(1 << k if k < 63 else -(1 << 63)) for k in range(64)])
    word = lambda i: F.coalesce(F.get("words", F.floor(i / 64).cast("int")), F.lit(0).cast("long"))
    kept = F.filter(lines, lambda x, i: word(i).bitwiseAND(F.get(one, i % 64)) == 0)
    d = d.join(bitmaps.select("doc", "text_hash", "n_dropped", _dense(F.col("dropped")).alias("words")), ["doc", "text_hash"], "left")
    return d.select(F.col("_id").alias(id_col), F.size(lines).cast("long").alias("n_lines"), F.coalesce("n_dropped", F.lit(0).cast("long")).alias("n_dropped"), F.when(F.col("words").isNull(), F.coalesce("_text", F.lit(""))).otherwise(F.array_join(kept, "\n")).alias(out))


def op6_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    kept = apply_bitmaps(docs, line_bitmaps(docs))
    return kept.select("doc_id", "n_lines", "n_dropped", F.sha2("kept_text", 256).alias("kept_sha256"))


QUERIES = {"op6_line_dedup": op6_line_dedup}

ORACLES = {
    "op6_line_dedup": r"""
WITH parts AS (SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line, generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS pos FROM documents),
keyed AS (SELECT doc_id, pos, line, translate(regexp_replace(line, '^[\x20\x09-\x0D]+|[\x20\x09-\x0D]+$', '', 'g'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS k FROM parts),
firsts AS (SELECT k, min(doc_id) AS first_doc FROM keyed WHERE length(k) >= 10 GROUP BY k HAVING count(DISTINCT doc_id) >= 2),
marked AS (SELECT keyed.doc_id, pos, line, coalesce(keyed.doc_id > first_doc, false) AS gone FROM keyed LEFT JOIN firsts ON keyed.k = firsts.k)
SELECT doc_id, count(*)::BIGINT AS n_lines, count(*) FILTER (gone)::BIGINT AS n_dropped, sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (NOT gone), '')) AS kept_sha256
FROM marked GROUP BY doc_id"""
}
