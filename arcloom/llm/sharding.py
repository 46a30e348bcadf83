"""Best-fit-decreasing bin packing of indivisible groups into shards.

Groups of one size are alike, so packing needs only how many groups have each size. That histogram is summed on the
executors; the number of distinct sizes in B bytes is at most sqrt(2 B), which bounds what the driver gets. The
driver packs runs of equal sizes through a balanced tree of remaining capacities (one step fills the tightest bin
with as many of the run as fit, which is what packing them one by one does), and the runs are joined back to the
groups by their rank within their size.

Null text: 8 bytes, in one group with the empty text. Null ids are kept. Repeated rows are members of one group.
Texts of any length are whole. Empty table: no rows. A group larger than an even share gets a shard of its own. Other columns are not read.
"""

from __future__ import annotations

import random
from collections.abc import Iterable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import gapless_rank, materialise, small, table


class Treap:
    """Balanced search tree of (remaining, bin)."""

    def __init__(self) -> None:
        self.root, self.dice = None, random.Random(7)

    def _split(self, t, key):
        if t is None:
            return None, None
        if t[0] < key:
            a, b = self._split(t[3], key)
            t[3] = a
            return t, b
        a, b = self._split(t[2], key)
        t[2] = b
        return a, t

    def _merge(self, a, b):
        if a is None or b is None:
            return a or b
        if a[1] > b[1]:
            a[3] = self._merge(a[3], b)
            return a
        b[2] = self._merge(a, b[2])
        return b

    def add(self, key: tuple[int, int]) -> None:
        a, b = self._split(self.root, key)
        self.root = self._merge(self._merge(a, [key, self.dice.random(), None, None]), b)

    def pop_at_least(self, size: int) -> tuple[int, int] | None:
        """Take out the smallest key whose remaining capacity is ``size`` or more."""
        a, b = self._split(self.root, (size, -1))
        if b is None:
            self.root = a
            return None
        least = b
        while least[2] is not None:
            least = least[2]
        _, rest = self._split(b, (least[0][0], least[0][1] + 1))
        self.root = self._merge(a, rest)
        return least[0]


def best_fit_decreasing(histogram: Iterable[tuple[int, int]], capacity: int, most_bins: int | None = None) -> tuple[list[tuple[int, int, int, int]], list[int]] | None:
    """Runs (size, first rank, end rank, bin) and the bins' fill; None if over ``most_bins`` bins are needed."""
    tree, fill, runs = Treap(), [], []
    for size, count in sorted(histogram, reverse=True):
        if size > capacity:
            raise ValueError(f"a group of {size} does not fit a shard of {capacity}")
        done = 0
        while done < count:
            found = tree.pop_at_least(size)
            if found is None:
                if most_bins is not None and len(fill) >= most_bins:
                    return None
                found = (capacity, len(fill))
                fill.append(0)
            left, b = found
            n = min(count - done, left // size) if size else count - done
            runs.append((size, done, done + n, b))
            fill[b] += n * size
            done += n
            tree.add((left - n * size, b))
    return runs, fill


def even_bins(histogram: list[tuple[int, int]], bins: int) -> list[tuple[int, int, int, int]]:
    """Runs that pack everything into ``bins`` bins of the least capacity that best fit manages.

    Groups over an even share of what is left get bins of their own first.
    """
    left, runs, used = {s: c for s, c in histogram}, [], 0
    given: dict[int, int] = {}
    while left and used < bins - 1:
        size, total = max(left), sum(s * c for s, c in left.items())
        if size * (bins - used) <= total:
            break
        runs.append((size, given.get(size, 0), given.get(size, 0) + 1, used))
        given[size] = given.get(size, 0) + 1
        used += 1
        left[size] -= 1
        if not left[size]:
            del left[size]
    if not left:
        return runs
    room, items = bins - used, list(left.items())
    low = max(max(left), -(-sum(s * c for s, c in items) // room))
    step, found = 1, best_fit_decreasing(items, low, room)
    high = low
    while found is None:
        low, high = high + 1, high + step
        step *= 2
        found = best_fit_decreasing(items, high, room)
    while low < high:
        middle = (low + high) // 2
        trial = best_fit_decreasing(items, middle, room)
        low, high, found = (low, middle, trial) if trial else (middle + 1, high, found)
    return runs + [(s, a + given.get(s, 0), b + given.get(s, 0), k + used) for s, a, b, k in found[0]]


def pack_groups(docs: DataFrame, shards: int | None = None, capacity: int | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, size, text_crc32, shard, slot): ``shards`` shards of near-equal bytes, or as few of ``capacity`` as best fit needs.

    With ``capacity``, a group that is larger raises ValueError.
    """
    spark = docs.sparkSession
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = materialise(docs.select(F.col(id_col).cast("long").alias("_id"), (F.octet_length(text) + 8).cast("long").alias("size"), F.crc32(F.encode(text, "UTF-8")).alias("text_crc32"), F.xxhash64(text).alias("h1"), F.xxhash64(F.lit(1), text).alias("h2")), "shard-rows")
    groups = rows.groupBy("h1", "h2").agg(F.sum("size").alias("bytes"), F.count("*").alias("n"))
    sizes = [(r["bytes"], r["groups"], r["n"]) for r in groups.groupBy("bytes").agg(F.count("*").alias("groups"), F.sum("n").alias("n")).toLocalIterator()]
    histogram, n_groups, n_rows = [(s, c) for s, c, _ in sizes], sum(c for _, c, _ in sizes), sum(n for _, _, n in sizes)
    if capacity is not None:
        runs = best_fit_decreasing(histogram, capacity)[0]
    else:
        runs = even_bins(histogram, shards or 1)
    placed = spark.createDataFrame(runs, "bytes long, a long, b long, shard int")
    ranked = gapless_rank(groups, ["bytes"], ["h1", "h2"], "rank", n_groups)
    where = ranked.join(small(placed, 28), "bytes").where("rank >= a and rank < b").select("h1", "h2", "shard")
    dealt = rows.join(where, ["h1", "h2"]).select("_id", "size", "text_crc32", "shard", "h1")
    return gapless_rank(dealt, ["shard"], ["_id", "h1"], "slot", n_rows).select(F.col("_id").alias(id_col), "size", "text_crc32", "shard", "slot")


def op5_sharding(spark: SparkSession, sf_dir: str, shards: int = 24) -> DataFrame:
    packed = pack_groups(table(spark, sf_dir, "documents"), shards)
    return packed.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


QUERIES = {"op5_sharding": op5_sharding}
ORACLES: dict[str, str] = {}
