"""Loops over DataFrames: every round is one plan, materialised reliably before the next."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession


def checkpoint_dir(spark: SparkSession) -> str:
    """The cluster's shared folder. Where none is set, one of our own in local mode; elsewhere that raises, as executors share no such folder."""
    sc = spark.sparkContext
    if not sc.getCheckpointDir():
        named = sc.getConf().get("spark.checkpoint.dir", None)
        if not named:
            if not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
                raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
            named = f"file://{tempfile.mkdtemp(prefix='arcloom-')}"
            atexit.register(shutil.rmtree, named.removeprefix("file://"), ignore_errors=True)
        sc.setCheckpointDir(named)
    return sc.getCheckpointDir()


def cut(df: DataFrame) -> DataFrame:
    """Materialise in the shared folder and cut the lineage. The data survives lost executors.

    A table is read back rather than a checkpoint: a checkpoint keeps the constraints that the optimizer has inferred,
    which multiply with every round of a loop.
    """
    path = f"{checkpoint_dir(df.sparkSession)}/cut-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._cut_to = path
    return out


def release(*tables: DataFrame | None) -> None:
    """Delete tables of ``cut`` that nothing reads any more, such as the state of an earlier round."""
    for df in tables:
        if path := getattr(df, "_cut_to", None):
            spark = df.sparkSession
            where = spark._jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).delete(where, True)


class Loop:
    """Rounds of ``step(state, round) -> (state, facts)`` until ``stop(facts)``, or ``most`` rounds if that is given.

    ``facts`` are a few scalars; they are all that reaches the driver, and make the trace.
    """

    def __init__(self, step: Callable, stop: Callable[[dict], bool], most: int | None = None):
        self.step, self.stop, self.most, self.trace, self.converged = step, stop, most, [], False

    def run(self, state):
        r = 0
        while self.most is None or r < self.most:
            r += 1
            state, facts = self.step(state, r)
            self.trace.append({"round": r} | facts)
            if self.stop(facts):
                self.converged = True
                break
        return state
