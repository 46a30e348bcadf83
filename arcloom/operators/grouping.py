"""Kernel 5: greedy grouping by an entropy objective.

Groups partition the vertices that are darker than alpha. Density is inner arcs over outer arcs. Three readings of
the objective: ``ratio`` (entropy of the density, as defined, clamped to 0..1), ``share`` (of the inner share), and
``cells`` (description length: entropy of the filled cells of every pair of groups, times cells), which is the one
that finds communities. The first two are not defined for a single group (nothing is outside), which counts as
infinite when the objective is to fall, so the first split always goes ahead.
"""

from __future__ import annotations

import math
from collections import Counter
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from arcloom import rng
from arcloom.functions.scalar import binary_entropy
from arcloom.model import PropertyGraph, induced
from arcloom.operators.metrics import brands, group_arcs
from arcloom.operators.search import Packed, local
from arcloom.plans.iterate import cut, release
from arcloom.sources.ingest import GRAPHS, SEED, SQL, stored


def induce(g: PropertyGraph, alpha: float) -> PropertyGraph:
    v = g.vertices.where(F.col("color") > alpha)
    return PropertyGraph(v, induced(g.edges.select("src", "dst", "weight"), v))


def density(g: PropertyGraph, groups: DataFrame) -> DataFrame:
    """(group, size, inner, outer, density) in arcs; density is null where nothing is outside."""
    arcs = group_arcs(g.edges.select("src", "dst"), groups)
    by = arcs.groupBy(F.col("g").alias("group")).agg(F.sum((F.col("g") == F.col("h")).cast("long")).alias("inner"), (2 * F.sum((F.col("g") != F.col("h")).cast("long"))).alias("outer"))
    size = groups.groupBy("group").agg(F.count("*").alias("size"))
    out = size.join(by, "group", "left").select("group", "size", F.coalesce("inner", F.lit(0)).alias("inner"), F.coalesce("outer", F.lit(0)).alias("outer"))
    return out.withColumn("density", F.col("inner") / F.nullif(F.col("outer"), F.lit(0)))


def objective(g: PropertyGraph, groups: DataFrame, kind: str = "ratio") -> DataFrame:
    """(objective) of one row."""
    if kind in ("ratio", "share"):
        d = density(g, groups)
        p = F.least(F.coalesce("density", F.lit(1.0)), F.lit(1.0)) if kind == "ratio" else F.coalesce(F.col("inner") / F.nullif(F.col("inner") + F.col("outer"), F.lit(0)), F.lit(0.0))
        return d.agg(F.sum(binary_entropy(p)).alias("objective"))
    if kind != "cells":
        raise ValueError(kind)
    size = cut(groups.groupBy("group").agg(F.count("*").alias("n")))
    filled = group_arcs(g.edges.select("src", "dst"), groups).groupBy("g", "h").agg(F.count("*").alias("k"))
    cells = filled.join(size.select(F.col("group").alias("g"), F.col("n").alias("ng")), "g").join(size.select(F.col("group").alias("h"), F.col("n").alias("nh")), "h")
    possible = F.when(F.col("g") == F.col("h"), F.col("ng") * (F.col("ng") - 1)).otherwise(F.col("ng") * F.col("nh"))
    return cells.agg(F.coalesce(F.sum(possible * binary_entropy(F.col("k") / possible)), F.lit(0.0)).alias("objective"))


def cut_size(g: PropertyGraph, groups: DataFrame) -> DataFrame:
    """(cut, largest, groups): edges across groups, largest group, number of groups."""
    across = group_arcs(g.edges.select("src", "dst"), groups).where("g <> h and src < dst").agg(F.count("*").alias("cut"))
    size = groups.groupBy("group").agg(F.count("*").alias("n")).agg(F.max("n").alias("largest"), F.count("*").alias("groups"))
    return across.crossJoin(size)


def _h(p: float) -> float:
    return 0.0 if p <= 0 or p >= 1 else -p * math.log2(p) - (1 - p) * math.log2(1 - p)


@dataclass
class Splitter:
    """The split loop with counts that a move changes by the degree of what moves."""

    adjacent: dict[int, list] | Packed
    kind: str = "ratio"
    direction: str = "decrease"
    skip_unsplittable: bool = False
    trace: list = field(default_factory=list)

    def __post_init__(self) -> None:
        self.group = dict.fromkeys(self.adjacent, 0)
        self.size = [len(self.adjacent)]
        packed = isinstance(self.adjacent, Packed)
        self.labels = np.zeros(len(self.adjacent), np.int64) if packed else None
        self.block = [[len(self.adjacent.to) if packed else sum(len(r) for r in self.adjacent.values())]]
        self.total = self._touching(0, 0)

    def _outer(self, g: int) -> int:
        return 2 * (sum(self.block[g]) - self.block[g][g])

    def _density(self, g: int) -> float:
        out = self._outer(g)
        return self.block[g][g] / out if out else math.inf

    def _term(self, g: int) -> float:
        inner, outer = self.block[g][g], self._outer(g)
        if self.kind == "ratio":
            return _h(min(1.0, inner / outer)) if outer else 0.0
        return _h(inner / (inner + outer)) if inner + outer else 0.0

    def _cell(self, g: int, h: int) -> float:
        cells = self.size[g] * (self.size[g] - 1) if g == h else self.size[g] * self.size[h]
        return cells * _h(self.block[g][h] / cells) if cells else 0.0

    def _touching(self, g: int, h: int) -> float:
        """The part of the objective that a move between g and h may change."""
        both = {g, h}
        if self.kind != "cells":
            return sum(self._term(x) for x in both if self.size[x])
        return sum(self._cell(x, y) * (1 if y in both else 2) for x in both for y in range(len(self.size)))

    def value(self) -> float:
        """The objective, kept up to date by moves."""
        if self.kind != "cells" and sum(s > 0 for s in self.size) == 1:
            return math.inf if self.direction == "decrease" else -math.inf
        return self.total

    def _groups_near(self, v: int):
        """(group, arcs of v into it)."""
        if self.labels is None:
            return Counter(self.group[u] for u, _ in self.adjacent[v]).items()
        return [(h, n) for h, n in enumerate(np.bincount(self.labels[self.adjacent.near(v)]).tolist()) if n]

    def move(self, v: int, to: int) -> None:
        own = self.group[v]
        before = self._touching(own, to)
        for h, n in self._groups_near(v):
            self.block[own][h] -= n
            self.block[h][own] -= n
            self.block[to][h] += n
            self.block[h][to] += n
        self.group[v] = to
        if self.labels is not None:
            self.labels[self.adjacent.at[v]] = to
        self.size[own] -= 1
        self.size[to] += 1
        self.total += self._touching(own, to) - before

    def run(self, m: int) -> int:
        """At most m rounds; returns the number of groups. ``trace`` has a row a round with the groups and the value after it."""
        stuck: set[int] = set()
        for r in range(1, m + 1):
            open_ = [g for g in range(len(self.size)) if self.size[g] and g not in stuck and not (self.skip_unsplittable and self.size[g] < 2)]
            if not open_:
                break
            g = min(open_, key=lambda x: (self._density(x), x))
            new = len(self.size)
            self.size.append(0)
            for row in self.block:
                row.append(0)
            self.block.append([0] * (new + 1))
            best, moved = self.value(), 0
            for v in sorted(x for x, own in self.group.items() if own == g):
                if self.size[g] == 1:
                    break
                self.move(v, new)
                now = self.value()
                if (now < best - 1e-12) if self.direction == "decrease" else (now > best + 1e-12):
                    best, moved = now, moved + 1
                else:
                    self.move(v, g)
            if not moved:
                self.size.pop()
                self.block.pop()
                for row in self.block:
                    row.pop()
                stuck.add(g)
            self.trace.append({"round": r, "group": g, "moved": moved, "objective": best, "k": sum(1 for s in self.size if s), "value": self.value()})
            if not moved and not self.skip_unsplittable:
                break
        return sum(1 for s in self.size if s)


def split(g: PropertyGraph, alpha: float, m: int, objective: str = "ratio", direction: str = "decrease", sweep: str = "sequential", skip_unsplittable: bool = False, fraction: float = 0.5, seed: int = SEED, most: int | None = None) -> DataFrame:
    """(id, group) after at most m rounds.

    ``sequential`` sweeps vertices in order in one task and, if asked to, refuses graphs over ``most`` arcs; ``batched`` sweeps on all
    tasks (``_split_batched``).
    """
    inner = induce(g, alpha)
    if sweep == "batched":
        return _split_batched(inner, m, objective, direction, fraction, seed, skip_unsplittable)

    def work(adjacent):
        s = Splitter(adjacent, objective, direction, skip_unsplittable)
        if adjacent:
            s.run(m)
        return s.group.items()

    return local(inner, "id long, group long", work, most)


def batched_gains(g: PropertyGraph, groups: DataFrame, target: int) -> DataFrame:
    """(id, inside, outside): arcs of every member of the target group to its own group and to others."""
    arcs = group_arcs(g.edges.select("src", "dst"), groups).where(F.col("g") == target)
    return arcs.groupBy(F.col("src").alias("id")).agg(F.sum((F.col("h") == target).cast("long")).alias("inside"), F.sum((F.col("h") != target).cast("long")).alias("outside"))


@dataclass
class Totals:
    """Sizes of groups and arcs between them: numbers that are bounded by the square of the number of groups."""

    size: list[int]
    block: list[list[int]]

    @classmethod
    def of(cls, g: PropertyGraph, groups: DataFrame, k: int) -> "Totals":
        size = {r["group"]: r["count"] for r in groups.groupBy("group").count().collect()}
        block = [[0] * k for _ in range(k)]
        for r in group_arcs(g.edges.select("src", "dst"), groups).groupBy("g", "h").count().collect():
            block[r["g"]][r["h"]] = r["count"]
        return cls([size.get(i, 0) for i in range(k)], block)

    def value(self, kind: str, direction: str) -> float:
        s = Splitter({}, kind, direction)
        s.size, s.block, live = self.size, self.block, [i for i, n in enumerate(self.size) if n]
        if kind == "cells":
            return sum(s._cell(x, y) for x in live for y in live)
        if len(live) == 1:
            return math.inf if direction == "decrease" else -math.inf
        return sum(s._term(x) for x in live)


def move_gains(g: PropertyGraph, groups: DataFrame, totals: Totals, s: int, t: int, kind: str) -> DataFrame:
    """(id, own, gain): by how much the objective falls if a member of s moved to t, or one of t to s, and all else stayed.

    A vertex brings its arcs by group, the rest are totals: the change is an expression of numbers of one row.
    """
    k = len(totals.size)
    member = groups.where(F.col("group").isin(s, t)).select("id", F.col("group").alias("own"))
    arcs = group_arcs(g.edges.select("src", "dst"), groups).where(F.col("g").isin(s, t))
    x = arcs.groupBy(F.col("src").alias("id")).agg(*[F.sum((F.col("h") == h).cast("long")).alias(f"x{h}") for h in range(k)])
    rows = member.join(x, "id", "left").na.fill(0)
    n, b = totals.size, totals.block

    def cell(cells, filled) -> Column:
        cells, filled = F.lit(cells).cast("double"), F.lit(filled).cast("double")
        return F.when(cells > 0, cells * binary_entropy(filled / cells)).otherwise(0.0)

    def term(inner, outer) -> Column:
        inner, outer = F.lit(inner).cast("double"), F.lit(outer).cast("double")
        if kind == "ratio":
            return F.when(outer > 0, binary_entropy(F.least(F.lit(1.0), inner / outer))).otherwise(0.0)
        return F.when(inner + outer > 0, binary_entropy(inner / (inner + outer))).otherwise(0.0)

    def change(a: int, z: int) -> Column:
        """Fall of the objective if the vertex moves from a to z."""
        at = lambda h: F.col(f"x{h}")
        if kind != "cells":
            degree = sum((at(h) for h in range(k)), F.lit(0))
            new = [(b[a][a] - 2 * at(a), sum(b[a]) - degree), (b[z][z] + 2 * at(z), sum(b[z]) + degree)]
            was = [(b[i][i], sum(b[i])) for i in (a, z)]
            return sum((term(i, 2 * (total - i)) for i, total in was), F.lit(0.0)) - sum((term(i, (total - i) * 2) for i, total in new), F.lit(0.0))
        out = cell(n[a] * (n[a] - 1), b[a][a]) - cell((n[a] - 1) * (n[a] - 2), b[a][a] - 2 * at(a))
        out += cell(n[z] * (n[z] - 1), b[z][z]) - cell((n[z] + 1) * n[z], b[z][z] + 2 * at(z))
        out += 2 * (cell(n[a] * n[z], b[a][z]) - cell((n[a] - 1) * (n[z] + 1), b[a][z] - at(z) + at(a)))
        for h in range(k):
            if h not in (a, z) and n[h]:
                out += 2 * (cell(n[a] * n[h], b[a][h]) + cell(n[z] * n[h], b[z][h]) - cell((n[a] - 1) * n[h], b[a][h] - at(h)) - cell((n[z] + 1) * n[h], b[z][h] + at(h)))
        return out

    return rows.select("id", "own", F.when(F.col("own") == s, change(s, t)).otherwise(change(t, s)).alias("gain"))


def _split_batched(g: PropertyGraph, m: int, kind: str, direction: str, fraction: float, seed: int, skip: bool = False, sweeps: int = 8) -> DataFrame:
    """Rounds that split the least dense group. The new group starts from the vertex that gains most alone, and its neighbours in the group;
    then sweeps score the members of both groups against the frozen grouping, and a hashed fraction of those that gain
    changes side, kept only if the objective improves, else half as many. The round stays only if it improves the whole.
    """
    g = PropertyGraph(cut(g.vertices), cut(g.edges))
    groups = cut(g.vertices.select("id", F.lit(0).cast("long").alias("group")))
    sign, k = (1.0 if direction == "decrease" else -1.0), 1
    totals = Totals.of(g, groups, 1)
    if not totals.size[0]:
        return groups
    best = totals.value(kind, direction)
    better = lambda x, y: sign * x < sign * y - 1e-9
    stuck: set[int] = set()
    for r in range(m):
        shape = Splitter({}, kind, direction)
        shape.size, shape.block = totals.size, totals.block
        whole = [i for i in range(k) if totals.size[i] and i not in stuck and not (skip and totals.size[i] < 2)]
        if not whole:
            break
        s, t = min(whole, key=lambda i: (shape._density(i), i)), k
        if totals.size[s] < 2:
            break
        wide = Totals([*totals.size, 0], [*[[*row, 0] for row in totals.block], [0] * (k + 1)])
        first = move_gains(g, groups, wide, s, t, kind).orderBy(F.desc(F.round(F.col("gain") * sign, 9)), "id").select("id").limit(1)
        start = cut(first.unionByName(g.edges.join(F.broadcast(first.withColumnRenamed("id", "src")), "src", "left_semi").select(F.col("dst").alias("id")).join(groups.where(F.col("group") == s), "id", "left_semi")).distinct())
        if start.count() == totals.size[s]:
            start = cut(first)
        trial = cut(_moved(groups, start.withColumn("to", F.lit(t).cast("long"))))
        now = Totals.of(g, trial, k + 1)
        value, share = now.value(kind, direction), fraction
        for sweep in range(sweeps):
            gains = move_gains(g, trial, now, s, t, kind).where(F.col("gain") * sign > 1e-9)
            go = cut(gains.where(rng.uniform(seed, f"move{r}:{sweep}", "id") < share).select("id", F.when(F.col("own") == s, t).otherwise(s).cast("long").alias("to")))
            if go.isEmpty():
                break
            tried = cut(_moved(trial, go))
            after = Totals.of(g, tried, k + 1)
            if after.size[s] and after.size[t] and better(after.value(kind, direction), value):
                release(trial)
                trial, now, value = tried, after, after.value(kind, direction)
            else:
                share /= 2
        if not better(value, best):
            if not skip:
                break
            stuck.add(s)
            continue
        groups, totals, best, k = trial, now, value, k + 1
    return groups


def _moved(groups: DataFrame, go: DataFrame) -> DataFrame:
    return groups.join(go, "id", "left").select("id", F.coalesce("to", "group").alias("group"))


def purity(groups: DataFrame, truth: DataFrame) -> DataFrame:
    """Share of vertices that are in the most frequent true class (id, label) of their group."""
    n = groups.join(truth, "id").groupBy("group", "label").agg(F.count("*").alias("n"))
    return n.groupBy("group").agg(F.max("n").alias("top"), F.sum("n").alias("n")).agg((F.sum("top") / F.sum("n")).alias("purity"))


ALPHA = 0.9


def k5_split_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = GRAPHS["copart"](spark, sf_dir)
    out = None
    for kind in ("ratio", "share", "cells"):
        k = split(g, ALPHA, 5, kind).agg(F.lit(kind).alias("objective"), F.countDistinct("group").alias("k"), F.count("*").alias("n"))
        out = k if out is None else out.unionByName(k)
    return out


def split_grid(g: PropertyGraph, alphas: list[float], rounds: list[int], kinds: list[str]) -> DataFrame:
    """(alpha, m, objective, k, value): the split loop over a grid of its inputs, a task an alpha."""
    out = None
    for alpha in alphas:

        def work(adjacent):
            for kind in kinds:
                s = Splitter(adjacent, kind)
                if adjacent:
                    s.run(max(rounds))
                for m in rounds:  # fewer rounds are the first of more
                    end = s.trace[min(m, len(s.trace)) - 1] if adjacent and m else {"k": int(bool(adjacent)), "value": None}
                    yield kind, m, end["k"], end["value"] if end["k"] > 1 else None

        one = local(induce(g, alpha), "objective string, m long, k long, value double", work, None).withColumn("alpha", F.lit(alpha))
        out = one if out is None else out.unionByName(one)
    return out


def k5_move_gains(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Change of the objective for every vertex that moves between the even and the odd ids."""
    g = stored(induce(GRAPHS["copart"](spark, sf_dir), 0.5))
    groups = g.vertices.select("id", (F.col("id") % 2).alias("group"))
    return move_gains(g, groups, Totals.of(g, groups, 2), 0, 1, "cells").select("id", "own", F.round("gain", 4).alias("gain"))


def k5_batched_round(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = induce(GRAPHS["copart"](spark, sf_dir), 0.5)
    return batched_gains(g, g.vertices.select("id", (F.col("id") % 2).alias("group")), 0)


def k5_density(spark: SparkSession, sf_dir: str) -> DataFrame:
    return density(GRAPHS["copart"](spark, sf_dir), brands(spark, sf_dir)).select("group", "size", "inner", "outer", F.round("density", 6).alias("density"))


def _objective(kind: str):
    return lambda spark, sf_dir: objective(GRAPHS["copart"](spark, sf_dir), brands(spark, sf_dir), kind).select(F.round("objective", 4).alias("objective"))


QUERIES = {
    "k5_induced": lambda spark, sf_dir: induce(GRAPHS["copart"](spark, sf_dir), ALPHA).edges.select("src", "dst", F.round("weight", 6).alias("weight")),
    "k5_density": k5_density,
    "k5_entropy": lambda spark, sf_dir: GRAPHS["copart"](spark, sf_dir).vertices.select("id", F.round(binary_entropy(F.col("color")), 6).alias("h")),
    "k5_objective_ratio": _objective("ratio"),
    "k5_objective_share": _objective("share"),
    "k5_objective_cells": _objective("cells"),
    "k5_cut": lambda spark, sf_dir: cut_size(GRAPHS["copart"](spark, sf_dir), brands(spark, sf_dir)),
    "k5_split_k": k5_split_k,
    "k5_split_batched": lambda spark, sf_dir: split(GRAPHS["copart"](spark, sf_dir), ALPHA, 3, "cells", sweep="batched"),
    "k5_batched_round": k5_batched_round,
    "k5_move_gains": k5_move_gains,
    "grid_optimise": lambda spark, sf_dir: split_grid(stored(GRAPHS["userseq"](spark, sf_dir)), [0.1, 0.2], [5, 10], ["ratio", "share", "cells"]).select("alpha", "m", "objective", "k", F.round("value", 4).alias("value")),
}

_G = "g AS (SELECT p_partkey AS id, p_brand AS \"group\" FROM part), a AS MATERIALIZED (SELECT x.\"group\" AS g, y.\"group\" AS h, src, dst FROM e JOIN g x ON x.id = src JOIN g y ON y.id = dst), z AS (SELECT \"group\" AS g, count(*) AS size FROM g GROUP BY 1), d AS (SELECT z.g AS \"group\", size, count(*) FILTER (a.g = h) AS \"inner\", 2 * count(*) FILTER (a.g <> h) AS \"outer\" FROM z LEFT JOIN a ON a.g = z.g GROUP BY 1, 2)"
_H = "CASE WHEN {0} <= 0 OR {0} >= 1 THEN 0.0 ELSE -{0} * log2({0}) - (1 - {0}) * log2(1 - {0}) END"
ORACLES = {
    "k5_move_gains": f"WITH {SQL['copart']}, w AS (SELECT id, id % 2 AS z FROM v WHERE color > 0.5), y AS MATERIALIZED (SELECT src, a.z AS g, b.z AS h FROM e JOIN w a ON a.id = src JOIN w b ON b.id = dst), t AS (SELECT (SELECT count(*) FROM w WHERE z = 0)::DOUBLE AS n0, (SELECT count(*) FROM w WHERE z = 1)::DOUBLE AS n1, count(*) FILTER (g = 0 AND h = 0)::DOUBLE AS b00, count(*) FILTER (g = 1 AND h = 1)::DOUBLE AS b11, count(*) FILTER (g = 0 AND h = 1)::DOUBLE AS b01 FROM y), x AS (SELECT w.id, w.z AS own, count(*) FILTER (h = w.z)::DOUBLE AS same, count(*) FILTER (h = 1 - w.z)::DOUBLE AS other FROM w LEFT JOIN y ON src = w.id GROUP BY 1, 2), u AS (SELECT id, own, same, other, CASE own WHEN 0 THEN n0 ELSE n1 END AS na, CASE own WHEN 0 THEN n1 ELSE n0 END AS nz, CASE own WHEN 0 THEN b00 ELSE b11 END AS baa, CASE own WHEN 0 THEN b11 ELSE b00 END AS bzz, b01 FROM x, t), c AS (SELECT id, own, unnest([{{'s': 1, 'n': na * (na - 1), 'b': baa}}, {{'s': -1, 'n': (na - 1) * (na - 2), 'b': baa - 2 * same}}, {{'s': 1, 'n': nz * (nz - 1), 'b': bzz}}, {{'s': -1, 'n': (nz + 1) * nz, 'b': bzz + 2 * other}}, {{'s': 2, 'n': na * nz, 'b': b01}}, {{'s': -2, 'n': (na - 1) * (nz + 1), 'b': b01 - other + same}}]) AS r FROM u), q AS (SELECT id, own, r.s AS s, r.n AS n, r.b / r.n AS p FROM c) SELECT id, own, round(sum(s * n * {_H.format('p')}), 4) AS gain FROM q GROUP BY 1, 2",
    "k5_induced": f"WITH {SQL['copart']} SELECT src, dst, round(weight, 6) AS weight FROM e WHERE src IN (SELECT id FROM v WHERE color > {ALPHA}) AND dst IN (SELECT id FROM v WHERE color > {ALPHA})",
    "k5_density": f"WITH {SQL['copart']}, {_G} SELECT *, round(\"inner\" / nullif(\"outer\", 0), 6) AS density FROM d",
    "k5_entropy": f"WITH {SQL['copart']} SELECT id, round({_H.format('color')}, 6) AS h FROM v",
    "k5_objective_ratio": f"WITH {SQL['copart']}, {_G}, p AS (SELECT least(coalesce(\"inner\" / nullif(\"outer\", 0), 1.0), 1.0) AS p FROM d) SELECT round(sum({_H.format('p')}), 4) AS objective FROM p",
    "k5_objective_share": f"WITH {SQL['copart']}, {_G}, p AS (SELECT coalesce(\"inner\" / nullif(\"inner\" + \"outer\", 0), 0.0) AS p FROM d) SELECT round(sum({_H.format('p')}), 4) AS objective FROM p",
    "k5_objective_cells": f"WITH {SQL['copart']}, {_G}, c AS (SELECT a.g, a.h, count(*) AS k FROM a GROUP BY 1, 2), p AS (SELECT k, CASE WHEN c.g = c.h THEN x.size * (x.size - 1) ELSE x.size * y.size END AS n FROM c JOIN z x ON x.g = c.g JOIN z y ON y.g = c.h), q AS (SELECT n, k / n AS p FROM p) SELECT round(sum(n * {_H.format('p')}), 4) AS objective FROM q",
    "k5_cut": f"WITH {SQL['copart']}, {_G} SELECT (SELECT count(*) FROM a WHERE g <> h AND src < dst) AS cut, max(size) AS largest, count(*) AS groups FROM z",
    "k5_batched_round": f"WITH {SQL['copart']}, w AS (SELECT id FROM v WHERE color > 0.5) SELECT src AS id, count(*) FILTER (dst % 2 = 0) AS inside, count(*) FILTER (dst % 2 = 1) AS outside FROM e WHERE src IN (SELECT id FROM w) AND dst IN (SELECT id FROM w) AND src % 2 = 0 GROUP BY 1",
}
