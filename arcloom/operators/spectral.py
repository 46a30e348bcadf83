"""Kernel 2: dominant eigenvector by the power method, and the walks it stands for.

A round is a sparse product: arcs, dealt by source once, meet the vector (which moves), and products are summed by
the other end. No matrix is ever made. The relative L1 change and the norm are the only numbers that reach the driver.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from arcloom import rng
from arcloom.model import PropertyGraph, small
from arcloom.plans.iterate import Loop, cut
from arcloom.sources.ingest import GRAPHS, SEED, SQL


@dataclass
class Spectrum:
    """``vector`` (id, x), the trace (round, theta, lambda), and whether theta fell to eps within the rounds."""

    vector: DataFrame
    trace: list[dict]
    converged: bool
    rayleigh: float | None = None

    @property
    def rounds(self) -> int:
        return len(self.trace)


def strength(g: PropertyGraph) -> DataFrame:
    """(id, strength): sum of a vertex's weights, isolated vertices at zero."""
    s = g.edges.groupBy(F.col("src").alias("id")).agg(F.sum("weight").alias("s"))
    return g.vertices.select("id").join(s, "id", "left").select("id", F.coalesce("s", F.lit(0.0)).alias("strength"))


def multiply(arcs: DataFrame, x: DataFrame, n: int) -> DataFrame:
    """(id, y) with y = A x."""
    return arcs.join(small(x.select(F.col("id").alias("src"), "x"), n), "src").groupBy(F.col("dst").alias("id")).agg(F.sum(F.col("weight") * F.col("x")).alias("y"))


def _normalised(g: PropertyGraph, normalize: str) -> DataFrame:
    """Arcs whose weights are divided by the strength of the end that is multiplied (column) or of the other (row)."""
    if normalize == "none":
        return g.edges
    end = {"column": "src", "row": "dst"}[normalize]
    s = strength(g).select(F.col("id").alias(end), "strength")
    return g.edges.join(s, end).select("src", "dst", (F.col("weight") / F.nullif(F.col("strength"), F.lit(0.0))).alias("weight")).na.fill(0.0, ["weight"])


def power(g: PropertyGraph, eps: float = 1e-6, max_iter: int = 50, start: str = "constant", normalize: str = "none", shift: float = 0.0, rayleigh: bool = False, seed: int = SEED) -> Spectrum:
    """The power method; ``shift`` adds a multiple of the vector, which breaks ties of opposite eigenvalues."""
    n = g.vertices.count()
    arcs = PropertyGraph(g.vertices, _normalised(g, normalize)).arcs("weight")
    x = g.vertices.select("id", F.lit(1.0 / max(n, 1)).alias("x"))
    if start == "hash":
        x = g.vertices.select("id", rng.uniform(seed, "start", "id").alias("x"))
        x = x.withColumn("x", F.col("x") / F.lit(x.agg(F.sum("x")).first()[0]))
    state = cut(x)

    def one(state: DataFrame, r: int):
        both = cut(state.join(multiply(arcs, state, n), "id", "left").select("id", "x", (F.coalesce("y", F.lit(0.0)) + F.col("x") * shift).alias("y")))
        norm, old = both.agg(F.sum(F.abs("y")), F.sum(F.abs("x"))).first()
        if not norm:
            return state, {"theta": 0.0, "lambda": 0.0, "empty": True}
        new = both.select("id", "x", (F.col("y") / norm).alias("y"))
        theta = new.agg(F.sum(F.abs(F.col("y") - F.col("x")))).first()[0] / old
        return new.select("id", F.col("y").alias("x")), {"theta": theta, "lambda": norm / old - shift}

    loop = Loop(one, lambda f: f["theta"] <= eps, max_iter)
    state = loop.run(state)
    converged = loop.converged and not any("empty" in t for t in loop.trace)
    quotient = None
    if rayleigh:
        a = state.join(multiply(arcs, state, n), "id").agg(F.sum(F.col("x") * F.col("y")), F.sum(F.col("x") * F.col("x"))).first()
        quotient = a[0] / state.agg(F.sum(F.col("x") * F.col("x"))).first()[0] if a[0] is not None else 0.0
    arcs.unpersist()
    return Spectrum(state, loop.trace, converged, quotient)


def walk(g: PropertyGraph, jump: DataFrame, damping: float, eps: float, max_iter: int) -> Spectrum:
    """x = damping * (walk along weights; stuck vertices jump) + (1 - damping) * jump, from x = jump (id, p)."""
    n = g.vertices.count()
    arcs = PropertyGraph(g.vertices, _normalised(g, "column")).arcs("weight")
    stuck = g.vertices.select("id").join(g.edges.select(F.col("src").alias("id")).distinct(), "id", "left_anti").withColumn("stuck", F.lit(True))
    base = cut(g.vertices.select("id").join(jump, "id", "left").join(stuck, "id", "left").select("id", F.coalesce("p", F.lit(0.0)).alias("p"), F.coalesce("stuck", F.lit(False)).alias("stuck")))
    state = base.select("id", F.col("p").alias("x"))

    def one(state: DataFrame, r: int):
        lost = state.join(base.where("stuck"), "id", "left_semi").agg(F.coalesce(F.sum("x"), F.lit(0.0))).first()[0]
        new = base.join(multiply(arcs, state, n), "id", "left").select("id", (damping * (F.coalesce("y", F.lit(0.0)) + lost * F.col("p")) + (1 - damping) * F.col("p")).alias("y"))
        both = cut(new.join(state, "id"))
        change, norm, old = both.agg(F.sum(F.abs(F.col("y") - F.col("x"))), F.sum("y"), F.sum("x")).first()
        return both.select("id", F.col("y").alias("x")), {"theta": (change or 0.0) / (old or 1.0), "lambda": norm}

    loop = Loop(one, lambda f: f["theta"] <= eps, max_iter)
    state = loop.run(state)
    arcs.unpersist()
    return Spectrum(state, loop.trace, loop.converged)


def pagerank(g: PropertyGraph, damping: float = 0.85, eps: float = 1e-6, max_iter: int = 50) -> Spectrum:
    return walk(g, g.vertices.select("id", F.lit(1.0 / max(1, g.vertices.count())).alias("p")), damping, eps, max_iter)


def rwr(g: PropertyGraph, seeds: DataFrame, restart: float = 0.15, eps: float = 1e-6, max_iter: int = 50) -> Spectrum:
    """Walks that return to the seeds (id)."""
    n = seeds.distinct().count()
    return walk(g, seeds.distinct().select("id", F.lit(1.0 / max(1, n)).alias("p")), 1 - restart, eps, max_iter)


def trace(s: Spectrum, spark: SparkSession) -> DataFrame:
    rows = [(t["round"], t["theta"], t["lambda"]) for t in s.trace]
    return spark.createDataFrame(rows, "round int, theta double, lambda double")


def _vector(s: Spectrum) -> DataFrame:
    return s.vector.select("id", F.round("x", 9).alias("x"))


def _power(name: str, **options):
    return lambda spark, sf_dir: _vector(power(GRAPHS[name](spark, sf_dir), **options))


def k2_eigenvalue(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = power(GRAPHS["copart"](spark, sf_dir), 0.0, 10, rayleigh=True)
    return spark.createDataFrame([(round(s.trace[-1]["lambda"], 5), round(s.rayleigh, 5))], "by_norm double, by_rayleigh double")


def k2_theta_trace(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = trace(power(GRAPHS["partsupp"](spark, sf_dir), 1e-6, 10), spark)
    return t.select("round", F.round("theta", 7).alias("theta"), F.round("lambda", 5).alias("lambda"))


def k2_strength(spark: SparkSession, sf_dir: str) -> DataFrame:
    return strength(GRAPHS["copart"](spark, sf_dir)).select("id", F.round("strength", 6).alias("strength"))


def k2_rwr_10(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = GRAPHS["copart"](spark, sf_dir)
    return _vector(rwr(g, g.vertices.where("color > 0.97").select("id"), 0.15, 0.0, 10))


QUERIES = {
    "k2_power_10": _power("copart", eps=0.0, max_iter=10),
    "k2_power_eps": _power("userseq", eps=1e-6, max_iter=50),
    "k2_power_random": _power("copart", eps=0.0, max_iter=5, start="hash"),
    "k2_power_shifted": _power("partsupp", eps=0.0, max_iter=10, shift=50.0),
    "k2_strength": k2_strength,
    "k2_pagerank_10": lambda spark, sf_dir: _vector(pagerank(GRAPHS["copart"](spark, sf_dir), 0.85, 0.0, 10)),
    "k2_rwr_10": k2_rwr_10,
    "k2_eigenvalue": k2_eigenvalue,
    "k2_theta_trace": k2_theta_trace,
}

def _head(graph: str) -> str:
    return "WITH " + SQL[graph].replace("e AS (", "e AS MATERIALIZED (", 1)


def sql_power(graph: str, rounds: int, start: str = "1.0::DOUBLE / (SELECT count(*) FROM v)", shift: float = 0.0) -> str:
    """Unrolled rounds: x0, then y1 and x1, ..."""
    out = [_head(graph), f"x0 AS MATERIALIZED (SELECT id, {start} AS x FROM v)"]
    for r in range(1, rounds + 1):
        out.append(f"y{r} AS MATERIALIZED (SELECT v.id, coalesce(y, 0.0) + {shift} * x AS y FROM v JOIN x{r - 1} USING (id) LEFT JOIN (SELECT dst AS id, sum(weight * x) AS y FROM e JOIN x{r - 1} ON id = src GROUP BY 1) USING (id))")
        out.append(f"n{r} AS MATERIALIZED (SELECT sum(abs(y)) AS n FROM y{r}), x{r} AS MATERIALIZED (SELECT id, y / (SELECT n FROM n{r}) AS x FROM y{r})")
    return ", ".join(out)


def _theta(r: int) -> str:
    return f"(SELECT sum(abs(b.x - a.x)) / sum(abs(a.x)) FROM x{r} b JOIN x{r - 1} a USING (id))"


def _sql_walk(graph: str, p: str, damping: float, rounds: int) -> str:
    out = [_head(graph), "s AS (SELECT src AS id, sum(weight) AS s FROM e GROUP BY 1)", f"x0 AS MATERIALIZED (SELECT id, coalesce(p, 0.0) AS x, coalesce(p, 0.0) AS p, s FROM v LEFT JOIN s USING (id) LEFT JOIN ({p}) USING (id))"]
    for r in range(1, rounds + 1):
        out.append(f"x{r} AS MATERIALIZED (SELECT a.id, {damping} * (coalesce(y, 0.0) + (SELECT coalesce(sum(x), 0.0) FROM x{r - 1} WHERE s IS NULL) * a.p) + {1 - damping} * a.p AS x, a.p, a.s FROM x{r - 1} a LEFT JOIN (SELECT dst AS id, sum(CASE WHEN s = 0 THEN 0 ELSE weight * x / s END) AS y FROM e JOIN x{r - 1} ON id = src GROUP BY 1) b ON a.id = b.id)")
    return ", ".join(out) + f" SELECT id, round(x, 9) AS x FROM x{rounds}"


_X = " SELECT id, round(x, 9) AS x FROM x"
#: Rounds that a run to a threshold may take in SQL: the first that meets it is returned.
_CAP = 25
ORACLES = {
    "k2_power_10": sql_power("copart", 10) + _X + "10",
    "k2_power_eps": sql_power("userseq", _CAP) + ", stop AS (SELECT min(r) AS r FROM (" + " UNION ALL ".join(f"SELECT {r} AS r, {_theta(r)} AS t" for r in range(1, _CAP + 1)) + ") WHERE t <= 1e-6)" + " UNION ALL ".join(f" SELECT id, round(x, 9) AS x FROM x{r} WHERE (SELECT r FROM stop) = {r}" for r in range(1, _CAP + 1)),
    "k2_power_random": sql_power("copart", 5, f"{rng.sql_uniform(SEED, 'start', 'id')} / (SELECT sum({rng.sql_uniform(SEED, 'start', 'id')}) FROM v)") + _X + "5",
    "k2_power_shifted": sql_power("partsupp", 10, shift=50.0) + _X + "10",
    "k2_strength": f"WITH {SQL['copart']} SELECT id, round(coalesce(sum(weight), 0.0), 6) AS strength FROM v LEFT JOIN e ON id = src GROUP BY 1",
    "k2_pagerank_10": _sql_walk("copart", "SELECT id, 1.0::DOUBLE / (SELECT count(*) FROM v) AS p FROM v", 0.85, 10),
    "k2_rwr_10": _sql_walk("copart", "SELECT id, 1.0::DOUBLE / (SELECT count(*) FROM v WHERE color > 0.97) AS p FROM v WHERE color > 0.97", 0.85, 10),
    "k2_eigenvalue": sql_power("copart", 10) + " SELECT round((SELECT n FROM n10), 5) AS by_norm, round((SELECT sum(a.x * e.weight * b.x) FROM e JOIN x10 a ON a.id = src JOIN x10 b ON b.id = dst) / (SELECT sum(x * x) FROM x10), 5) AS by_rayleigh",
    "k2_theta_trace": sql_power("partsupp", 10) + " " + " UNION ALL ".join(f"SELECT {r}::INTEGER AS round, round({_theta(r)}, 7) AS theta, round((SELECT n FROM n{r}), 5) AS lambda" for r in range(1, 11)),
}
