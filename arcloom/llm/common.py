"""Helpers that the training-data operators share."""

from __future__ import annotations

import atexit
import contextlib
import ctypes
import math
import shutil
import tempfile
import uuid
from collections.abc import Iterable, Sequence

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

# Arrow's own pool keeps what tasks have freed; the system's gives it back (``tidy``).
pa.set_memory_pool(pa.system_memory_pool())

#: The ASCII white space of the contracts, and the letters that are lowered.
SPACES = " \t\n\x0b\f\r"
UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER = "abcdefghijklmnopqrstuvwxyz"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def unused(taken: Iterable[str], *wanted: str) -> str | list[str]:
    """Column names that none of ``taken`` clashes with, whatever its case."""
    seen = {c.lower() for c in taken}
    out = []
    for name in wanted:
        while name.lower() in seen:
            name += "_"
        seen.add(name.lower())
        out.append(name)
    return out if len(out) > 1 else out[0]


def shared_dir(spark: SparkSession) -> str:
    """The folder that the cluster names for checkpoints. Where none is named, one of our own in local mode; elsewhere that raises, as executors share no such folder."""
    sc = spark.sparkContext
    named = sc.getConf().get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not named:
        if not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        named = f"file://{tempfile.mkdtemp(prefix='arcloom-')}"
        atexit.register(shutil.rmtree, named.removeprefix("file://"), ignore_errors=True)
        sc.setCheckpointDir(named)
    return named.rstrip("/")


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` once to the shared folder and read it back: short lineage that survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/arcloom/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._written_to = path
    return out


def release(*tables: DataFrame | None) -> None:
    """Delete materialised tables that nothing reads any more."""
    for df in tables:
        if path := getattr(df, "_written_to", None):
            jvm = df.sparkSession._jvm
            where = jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(df.sparkSession._jsparkSession.sessionState().newHadoopConf()).delete(where, True)


#: Bytes up to which a counted table is broadcast.
BROADCAST_BYTES = 32 << 20


def small(df: DataFrame, row_bytes: int = 24) -> DataFrame:
    """``df`` to be broadcast if its rows, which are counted, are within bounds; else a join shuffles it."""
    return F.broadcast(df) if df.count() * row_bytes <= BROADCAST_BYTES else df


def gapless_rank(df: DataFrame, keys: Sequence[str], order: Sequence[str], out: str, rows: int, per_part: int = 100_000) -> DataFrame:
    """Number the rows of each key from 0 without gaps, in parts of about ``per_part`` rows.

    A plain window would put a whole key into one task. Here the rows of a key are dealt into hashed
    parts, numbered inside a part, and shifted by the sizes of the parts before it.
    """
    parts = max(1, math.ceil(rows / per_part))
    df = df.withColumn("_part", F.pmod(F.xxhash64(*order), F.lit(parts)))
    by = [*keys, "_part"]
    before = Window.partitionBy(*keys).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1) if keys else Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    shift = df.groupBy(*by).agg(F.count("*").alias("_n")).withColumn("_shift", F.coalesce(F.sum("_n").over(before), F.lit(0))).drop("_n")
    own = Window.partitionBy(*by).orderBy(*order)
    ranked = df.withColumn("_own", F.row_number().over(own) - 1)
    cond = [ranked[k].eqNullSafe(shift[k]) for k in by]
    return ranked.join(shift, cond).select(*[ranked[c] for c in ranked.columns if c not in ("_own", "_part")], (F.col("_own") + F.col("_shift")).cast("long").alias(out))


_PUNCT = {c: " " for c in range(128) if not (48 <= c <= 57 or 65 <= c <= 90 or 97 <= c <= 122)}


def words(text: str | None) -> list[str]:
    """Lower-case words; every ASCII character but letters and digits ends a word."""
    return text.lower().translate(_PUNCT).split() if text else []


class TokenHasher:
    """Words to 64-bit hashes by way of a bounded cache."""

    def __init__(self, most: int = 100_000):
        self.most, self.seen = most, {}

    def __call__(self, tokens: list[str]) -> np.ndarray:
        seen = self.seen
        if len(seen) > self.most:
            seen.clear()
        for w in set(tokens).difference(seen):
            seen[w] = xxhash.xxh64_intdigest(w)
        return np.fromiter(map(seen.__getitem__, tokens), np.uint64, len(tokens))


def tidy() -> None:
    """Give memory that a task has freed back to the system; Python workers live on for the next stage."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


def slices(sizes: Sequence[int], most: int) -> list[tuple[int, int]]:
    """Cut positions 0..len(sizes) into runs whose sizes sum to about ``most``."""
    out, begin, total = [], 0, 0
    for i, n in enumerate(sizes):
        if total and total + n > most:
            out.append((begin, i))
            begin, total = i, 0
        total += n
    if begin < len(sizes):
        out.append((begin, len(sizes)))
    return out
