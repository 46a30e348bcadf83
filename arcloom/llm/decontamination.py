"""Benchmark decontamination by spaced-seed hashing.

A mask is a fixed pattern of token positions; those it leaves out may be substituted. Every position of every benchmark
item and of every document is hashed under every mask, and equal hashes are hits. The masks are few and light enough
that every overlap that counts has a hit (shown by enumeration in the tests), so nothing is lost to the search.
Hits near which no stretch can be similar enough are dropped at once, and on the diagonals of the others item and
document are compared token by token.

An overlap counts when it begins and ends with a match, is long enough and similar enough. On a diagonal the
one that scores best (a match 1, a substitution -2) is taken, else the one that exceeds the wanted identity most, and
what lies left and right of it is searched again: a diagonal with an overlap that counts always yields one.

Benchmark items are the stated query set. They are taken in blocks of at most ``block_items`` items and
``block_chars`` characters; a block's hash table is bounded and goes to every task, and the documents are scanned
once per block, so a benchmark of any size is matched whole without a shuffle of document hashes.

Null or empty texts match nothing. Very long texts are searched whole, a few MB of words at a time. Items under ``min_item`` words are too general and are not searched. Items shorter
than ``min_overlap`` words must be matched over their whole length, whose ends may be substituted. Null ids pass through. Repeated rows
each get a row. Empty tables: no rows. Other columns are not read.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import TokenHasher, slices, table, tidy, words

#: The masks; 1 is a position that is hashed. At identity 0.75 the first miss no overlap of 12 words or more, the others none of 5 or more.
MASKS = ("11101", "100111")
SHORT_MASKS = ("111", "1101")
FILTER_BITS = 20
#: Hits that are looked at together.
HITS = 1 << 15
SPAN = "array<struct<item_id:long,doc_start:int,doc_end:int,item_start:int,matched:int>>"


def _multipliers(n: int) -> np.ndarray:
    return (np.arange(1, n + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)) | np.uint64(1)


def seed_hashes(tokens: np.ndarray, mask: str) -> np.ndarray:
    """Hash of every window under the mask."""
    n = len(tokens) - len(mask) + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    on = [i for i, c in enumerate(mask) if c == "1"]
    h = np.zeros(n, np.uint64)
    for i, k in zip(on, _multipliers(len(on)), strict=True):
        h ^= tokens[i : i + n] * k
        h = (h << np.uint64(27) | h >> np.uint64(37)) * np.uint64(0xBF58476D1CE4E5B9)
    return h


def masks_for(need: int, identity: float) -> tuple[str, ...]:
    """Masks of which every overlap of ``need`` words or more has a seed; where those given do not suffice, the run of matches that must be there."""
    if identity >= 0.75 and need >= 5:
        return MASKS if need >= 12 else SHORT_MASKS
    off = [(n, int(n * (1 - identity) + 1e-9)) for n in range(need, 2 * need)]
    return ("1" * max(1, min(-(-(n - k) // (k + 1)) for n, k in off)),)


def _best(score: np.ndarray, same: np.ndarray, need: int) -> tuple[int, int]:
    """The stretch of ``need`` words or more between two matches that scores most; of equal ones a long one. (0, 0): none."""
    n = len(score) - need + 1
    if n <= 0:
        return 0, 0
    before = np.concatenate([[0.0], np.cumsum(score)])
    start = np.where(same[:n], before[:n], np.inf)
    value = np.where(same[need - 1 :], before[need:] - np.minimum.accumulate(start), -np.inf)
    end = n - 1 - int(np.argmax(value[::-1]))
    return (int(np.argmin(start[: end + 1])), end + need) if np.isfinite(value[end]) else (0, 0)


def windows(same: np.ndarray, need: int, identity: float) -> list[tuple[int, int]]:
    """Disjoint stretches of ``need`` words or more with matching ends and the identity; none is left beside them."""
    out, todo = [], [(0, len(same))]
    while todo:
        a, b = todo.pop()
        part = same[a:b]
        for score in (np.where(part, 1.0, -2.0), part - identity):
            start, end = _best(score, part, need)
            if end and part[start:end].sum() >= identity * (end - start) - 1e-9:
                out.append((a + start, a + end))
                todo += [(a, a + start), (a + end, b)]
                break
    return sorted(out)


class SeedIndex:
    """Sorted seed hashes of a block of items. Items shorter than ``min_overlap`` have masks of their own."""

    def __init__(self, items: list[tuple[int, str]], min_item: int, min_overlap: int, identity: float):
        self.min_overlap, self.identity = min_overlap, identity
        hasher, self.items, self.ids = TokenHasher(), [], []
        found: dict[tuple[bool, str], list[tuple[np.ndarray, int]]] = defaultdict(list)
        for item_id, text in items:
            tokens = hasher(words(text))
            if len(tokens) < max(1, min_item):
                continue
            for mask in masks_for(min(min_overlap, len(tokens)), identity):
                found[len(tokens) < min_overlap, mask].append((seed_hashes(tokens, mask), len(self.items)))
            self.items.append(tokens)
            self.ids.append(item_id)
        self.length = np.array([len(x) for x in self.items], np.int64)
        self.begin = np.cumsum(self.length) - self.length
        self.flat = np.concatenate(self.items) if self.items else np.zeros(0, np.uint64)
        self.tables = {}
        for key, rows in found.items():
            h = np.concatenate([x for x, _ in rows])
            item = np.concatenate([np.full(len(x), i) for x, i in rows])
            pos = np.concatenate([np.arange(len(x)) for x, _ in rows])
            order = np.argsort(h, kind="stable")
            bits = np.zeros(1 << FILTER_BITS, bool)
            bits[(h & np.uint64((1 << FILTER_BITS) - 1)).astype(np.int64)] = True
            self.tables[key] = (h[order], item[order], pos[order], bits)

    def _near(self, short: bool, tokens: np.ndarray, item: np.ndarray, where: np.ndarray, pos: np.ndarray) -> np.ndarray:
        """Hits around which some stretch is long and similar enough. One of twice the length has a half that is, so lengths under that suffice."""
        need = self.min_overlap
        around = np.arange(need - 1) - pos[:, None] if short else np.arange(1 - 2 * need, 2 * need + 8)
        at, to = pos[:, None] + around, where[:, None] + around
        inside = (at >= 0) & (at < self.length[item][:, None]) & (to >= 0) & (to < len(tokens))
        same = inside & (self.flat[np.where(inside, self.begin[item][:, None] + at, 0)] == tokens[np.where(inside, to, 0)])
        if short:
            return same.sum(1) >= self.identity * self.length[item] - 1e-9
        upto = np.concatenate([np.zeros((len(item), 1), np.int32), np.cumsum(same, 1, dtype=np.int32)], 1)
        ok = np.zeros(len(item), bool)
        for n in range(need, 2 * need):
            ok |= (upto[:, n:] - upto[:, :-n]).max(1) >= self.identity * n - 1e-9
        return ok

    def hits(self, tokens: np.ndarray) -> np.ndarray:
        """Rows of (item, diagonal, document position) that are worth a comparison."""
        found = [np.zeros((0, 3), np.int64)]
        for (short, mask), (h, item, pos, bits) in self.tables.items():
            seeds = seed_hashes(tokens, mask)
            at = np.flatnonzero(bits[(seeds & np.uint64((1 << FILTER_BITS) - 1)).astype(np.int64)])
            a, b = np.searchsorted(h, seeds[at], "left"), np.searchsorted(h, seeds[at], "right")
            at, a, n = at[b > a], a[b > a], (b - a)[b > a]
            for i, j in slices(n.tolist(), HITS):
                m = n[i:j]
                where = np.repeat(at[i:j], m)
                row = np.repeat(a[i:j] - (np.cumsum(m) - m), m) + np.arange(m.sum())
                ok = self._near(short, tokens, item[row], where, pos[row])
                row, where = row[ok], where[ok]
                found.append(np.stack([item[row], where - pos[row], where], 1))
        return np.concatenate(found)

    def spans(self, tokens: np.ndarray, first: int, last: int, diagonals: set[tuple[int, int]]) -> list[dict]:
        """Overlaps in tokens[first:last] that count, on the given diagonals."""
        doc, out = tokens[first:last], []
        for i, diagonal in sorted(diagonals):
            d, item = diagonal - first, self.items[i]
            low, high = max(0, -d), min(len(item), len(doc) - d)
            same = doc[low + d : high + d] == item[low:high]
            if len(item) < self.min_overlap:
                whole = high - low == len(item) and same.sum() >= self.identity * len(item) - 1e-9
                found = [(0, len(item))] if whole else []
            else:
                found = windows(same, self.min_overlap, self.identity)
            out += [{"item_id": self.ids[i], "doc_start": d + low + a, "doc_end": d + low + b, "item_start": low + a, "matched": int(same[a:b].sum())} for a, b in found]
        return out


def _blocks(items: DataFrame, item_col: str, text_col: str, block_items: int, block_chars: int) -> Iterator[list[tuple[int, str]]]:
    held, chars = [], 0
    for r in items.select(F.col(item_col).cast("long"), F.col(text_col)).where(F.length(text_col) > 0).toLocalIterator():
        if held and (len(held) >= block_items or chars + len(r[1]) > block_chars):
            yield held
            held, chars = [], 0
        held.append((r[0], r[1]))
        chars += len(r[1])
    if held:
        yield held


def find_overlaps(docs: DataFrame, items: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", min_overlap: int = 12, identity: float = 0.75, min_item: int = 5, block_items: int = 20_000, block_chars: int = 1 << 24) -> DataFrame:
    """(row, id, spans) of the documents with an overlap; ``row`` is the text's hash.

    Positions are in words (lower case, ASCII punctuation apart), ends are exclusive.
    """
    spark = docs.sparkSession
    d = docs.select(F.col(id_col).cast("long").alias("id"), F.xxhash64(text_col).alias("row"), F.col(text_col).cast("string").alias("text"))
    out = None
    for block in _blocks(items, item_col, text_col, block_items, block_chars):
        shared = spark.sparkContext.broadcast(SeedIndex(block, min_item, min_overlap, identity))

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            for batch, a, found in _search(batches, shared.value, "text"):
                if found:
                    at = pa.array([a + k for k in found])
                    spans = pa.array(list(found.values()), pa.list_(pa.struct([("item_id", pa.int64()), ("doc_start", pa.int32()), ("doc_end", pa.int32()), ("item_start", pa.int32()), ("matched", pa.int32())])))
                    yield pa.RecordBatch.from_arrays([batch.column("id").take(at), batch.column("row").take(at), spans], names=["id", "row", "spans"])

        part = d.mapInArrow(run, f"id long, row long, spans {SPAN}")
        out = part if out is None else out.unionByName(part)
    if out is None:
        return spark.createDataFrame([], f"id long, row long, spans {SPAN}")
    return out


def _search(batches: Iterator[pa.RecordBatch], index: SeedIndex, text_col: str | int, hasher: TokenHasher | None = None) -> Iterator[tuple[pa.RecordBatch, int, dict[int, list[dict]]]]:
    """For slices of batches: the batch, where the slice begins, and the spans by row of the slice."""
    hasher = hasher or TokenHasher()
    for batch in batches:
        texts = batch.column(text_col)
        for a, b in slices(pc.fill_null(pc.utf8_length(texts), 0).to_pylist(), 1 << 21):
            lists = [words(t) for t in texts.slice(a, b - a).to_pylist()]
            ends = np.cumsum([len(x) for x in lists])
            tokens = hasher([w for x in lists for w in x])
            hits = index.hits(tokens)
            by_doc: dict[int, set] = defaultdict(set)
            for k, item, diagonal in zip(np.searchsorted(ends, hits[:, 2], "right").tolist(), hits[:, 0].tolist(), hits[:, 1].tolist(), strict=True):
                by_doc[k].add((item, diagonal))
            yield batch, a, {k: s for k, on in sorted(by_doc.items()) if (s := index.spans(tokens, int(ends[k]) - len(lists[k]), int(ends[k]), on))}


def decontaminate(docs: DataFrame, items: DataFrame, text_col: str = "text", item_col: str = "item_id", min_overlap: int = 12, identity: float = 0.75, min_item: int = 5, block_items: int = 20_000, block_chars: int = 1 << 24) -> DataFrame:
    """``docs`` with all columns, without the rows that overlap an item. No exchange: a scan drops them."""
    at = docs.columns.index(text_col)
    for block in _blocks(items, item_col, text_col, block_items, block_chars):
        shared = docs.sparkSession.sparkContext.broadcast(SeedIndex(block, min_item, min_overlap, identity))

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            hasher = TokenHasher()
            for batch in batches:
                keep = np.ones(batch.num_rows, bool)
                keep[[a + k for _, a, found in _search(iter([batch]), shared.value, at, hasher) for k in found]] = False
                yield batch.filter(pa.array(keep))
            tidy()

        docs = docs.mapInArrow(run, docs.schema)
    return docs


def op7_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The contaminated documents: ids, items and overlaps."""
    found = find_overlaps(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return found.select(F.col("id").alias("doc_id"), F.array_sort(F.array_distinct(F.transform("spans", lambda s: s["item_id"]))).alias("item_ids"), "spans")


QUERIES = {"op7_decontamination": op7_decontamination}
ORACLES: dict[str, str] = {}
