"""N-gram language model in Elias-Fano tries, and scoring of documents by it.

Texts become blocks of token ids. Every window (w1, w2, w3) belongs to a shard by its middle word, so a shard has all
it takes to predict w3 after w2 and after w1 w2. A block sends each shard its distinct windows with their counts in
training documents; the shard adds the counts of all blocks, builds its trie, answers every window of every block
from the trie, and the answers go back to their blocks. Counts, tries and queries thus cover all documents, shards
are as many as the tokens need, and no model has to fit one machine.

Frequent contexts are dealt finer, which changes no score. The windows of a hot middle word (``hot`` windows or more)
belong to a shard by the pair (w1, w2), which has all that the pair needs; the pairs (w2, w3) are counted apart, as the
context of any word before w2. That context, and a pair that is hot itself (as the begin of a text is), is split:
its windows belong to a shard by the whole window, the shard answers counts, and the few totals of split
contexts are summed over shards.

The trie of a shard. Level 1 has the middle words. Level 2 has the successors of a middle word, and, read backwards,
the words before it. Level 3 has, for a pair (w1, w2), the words that follow it, stored as positions among the
successors of w2 alone (context-relative): a window is found by a successor search under w2, and a second one under
the pair for the small number that the first gave. Begin pointers and ids of all levels are monotone sequences in
Elias-Fano form; ids become monotone by adding the range's offset. Smoothed probabilities are stored as
16-bit logarithms, rounded so that they never gain mass. The bytes of a trie are used in place, in a memory map of
the task or as a table's binary value: windows are searched for in order, and only stretches of a level that are
asked for are decoded, one at a time.

P(w3 | w1 w2) = a3 + b3 * (a2 + b2 * p1(w3)), p1 = (c + 1) / (N + V + 1). With c the count of a successor, C the sum and S
the number of a context's successors, a = c / (C + S) and b = S / (C + S): what is left to the shorter context is the
share of new successors among all that the context has seen (Witten-Bell). No constant is estimated, so a score depends on the
training documents alone, not on how they are dealt. Sums over all words and one unknown word are at most one.

Null or empty text: the end token alone. Null ids are in the training part, held_out false. Repeated rows count and are
scored each. Very long texts are scored whole. No training documents: every word is unknown. Empty table: no rows.
Other columns are not read.
"""

from __future__ import annotations

import mmap
import struct
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import materialise, slices, table, tidy

#: Middle words: what stands before a text, and any word; words are hashes above them.
BEGIN, ANY = 2, 3
#: Neighbours: the begin, the end, words as the upper 40 of the 62 bits of their hash, any word. Two words are confused only where both follow, or both go before, one middle word.
NEAR_BEGIN, NEAR_END, NEAR_ANY, NEAR_SHIFT = 0, 1, 1 << 40, np.uint64(22)
#: Codes of logarithms: steps per unit, and the code of nothing. Values of a sequence that are decoded at a time.
STEPS, NOTHING = 512, 65535
STRETCH = 65536
#: There are at most so many hot words, and as many hot pairs, whatever the corpus: 24 bytes each are broadcast.
MOST_HOT = 1 << 20


# ---------------------------------------------------------------- Elias-Fano


class EliasFano:
    """A non-decreasing sequence of non-negative integers below 2**62."""

    def __init__(self, n: int, low_bits: int, low: np.ndarray, high: np.ndarray, sample: np.ndarray):
        self.n, self.low_bits, self.low, self.high, self.sample = n, low_bits, low, high, sample

    @classmethod
    def of(cls, values: np.ndarray) -> "EliasFano":
        values = np.asarray(values, np.int64)
        n = len(values)
        top = int(values[-1]) if n else 0
        bits = max(0, (max(1, top // max(1, n))).bit_length() - 1)
        low = np.zeros(0, np.uint8)
        if bits:  # 2**16 values at a time, whose bits fill whole bytes
            part = [np.unpackbits((values[i : i + 65536] & ((1 << bits) - 1)).astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, count=bits, bitorder="little") for i in range(0, n, 65536)]
            low = np.concatenate([np.packbits(x.ravel(), bitorder="little") for x in part])
        ones = (values >> bits) + np.arange(n)
        mask = np.zeros(int(ones[-1]) + 1 if n else 0, bool)
        mask[ones] = True
        return cls(n, bits, low, np.packbits(mask, bitorder="little"), ones[::256].astype("<u8"))

    def to_bytes(self) -> bytes:
        return struct.pack("<5Q", self.n, self.low_bits, len(self.low), len(self.high), len(self.sample)) + self.low.tobytes() + self.high.tobytes() + self.sample.tobytes()

    @classmethod
    def view(cls, data, at: int) -> tuple["EliasFano", int]:
        """A view of bytes at an offset, without copying, and where it ends."""
        n, bits, a, b, c = struct.unpack_from("<5Q", data, at)
        at += 40
        return cls(n, bits, np.frombuffer(data, np.uint8, a, at), np.frombuffer(data, np.uint8, b, at + a), np.frombuffer(data, "<u8", c, at + a + b)), at + a + b + 8 * c

    def decode(self, begin: int = 0, end: int | None = None) -> np.ndarray:
        """Elements begin..end; ``begin`` is a multiple of STRETCH."""
        end = self.n if end is None else min(end, self.n)
        if begin >= end:
            return np.zeros(0, np.int64)
        first = int(self.sample[begin // 256])
        last = int(self.sample[end // 256]) if end % 256 == 0 and end < self.n else 8 * len(self.high)
        ones = np.flatnonzero(np.unpackbits(self.high[first >> 3 : -(-last // 8)], bitorder="little")) + (first & ~7)
        ones = ones[np.searchsorted(ones, first) :][: end - begin]
        out = (ones - np.arange(begin, end)) << self.low_bits
        for i in range(begin, end if self.low_bits else begin, STRETCH):
            size = min(STRETCH, end - i)
            bits = np.unpackbits(self.low[i * self.low_bits // 8 :], count=size * self.low_bits, bitorder="little").reshape(size, self.low_bits)
            wide = np.zeros((size, 64), np.uint8)
            wide[:, : self.low_bits] = bits
            out[i - begin : i - begin + size] |= np.packbits(wide, axis=1, bitorder="little").view("<i8")[:, 0]
        return out

    def locate(self, values: np.ndarray) -> np.ndarray:
        """Position of each value, -1 where it is not: a successor search that decodes the stretches asked for, one at a time. Values may be in any order."""
        out = np.full(len(values), -1, np.int64)
        if not self.n or not len(values):
            return out
        order = np.argsort(values, kind="stable")
        asked = values[order]
        begins = np.arange(0, self.n, STRETCH)
        high = (self.sample[begins // 256].astype(np.int64) - begins) << self.low_bits  # no element of the stretch is below
        low, top = np.searchsorted(asked, high), np.append(np.searchsorted(asked, high[1:] + (1 << self.low_bits)), len(asked))
        for begin, i, j in zip(begins.tolist(), low.tolist(), top.tolist(), strict=True):
            if i < j:
                x = self.decode(begin, begin + STRETCH)
                at = np.searchsorted(x, asked[i:j])
                at[at == len(x)] = 0
                hit = x[at] == asked[i:j]
                out[order[i:j][hit]] = begin + at[hit]
        return out

    def gather(self, at: np.ndarray) -> np.ndarray:
        """Elements at non-decreasing positions, by stretches."""
        out = np.empty(len(at), np.int64)
        edges = np.searchsorted(at, np.arange(0, self.n + STRETCH, STRETCH))
        for k, (i, j) in enumerate(zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True)):
            if i < j:
                out[i:j] = self.decode(k * STRETCH, (k + 1) * STRETCH)[at[i:j] - k * STRETCH]
        return out

    def __getitem__(self, i: int) -> int:
        """One element: from the sampled position before it, ones are counted byte by byte."""
        at, left = int(self.sample[i // 256]), i % 256
        while left:
            byte, shift = at >> 3, (at & 7) + 1
            rest = int(self.high[byte]) >> shift
            if rest.bit_count() < left:
                left -= rest.bit_count()
                at = (byte << 3) + 7
                byte += 1
                while self.high[byte] == 0 or int(self.high[byte]).bit_count() < left:
                    left -= int(self.high[byte]).bit_count()
                    byte += 1
                rest, at = int(self.high[byte]), (byte << 3) - 1
            step = 0
            while left:
                step += 1
                left -= rest & 1
                rest >>= 1
            at += step
        low = 0
        for k in range(self.low_bits):
            j = i * self.low_bits + k
            low |= (int(self.low[j >> 3]) >> (j & 7) & 1) << k
        return (at - i) << self.low_bits | low

    def find(self, value: int, begin: int, end: int) -> int:
        """Position of the first element of begin..end that is ``value`` or more."""
        while begin < end:
            middle = (begin + end) // 2
            if self[middle] < value:
                begin = middle + 1
            else:
                end = middle
        return begin


# ---------------------------------------------------------------- trie


def code_of(p: np.ndarray) -> np.ndarray:
    with np.errstate(divide="ignore"):
        c = np.ceil(-np.log10(np.maximum(p, 1e-300)) * STEPS)
    return np.where(p <= 0, NOTHING, np.clip(c, 0, NOTHING)).astype("<u2")


VALUES = np.append(10.0 ** (-np.arange(NOTHING) / STEPS), 0.0)


def value_of(code: np.ndarray) -> np.ndarray:
    return VALUES[code]


def _smoothed(count: np.ndarray, total: np.ndarray, kinds: np.ndarray, of: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Codes of successors (a) and of contexts (b); ``of`` is the context of a successor."""
    with np.errstate(divide="ignore", invalid="ignore"):
        return code_of(count / (total + kinds)[of]), code_of(np.where(kinds > 0, kinds / (total + kinds), 1.0))


class Trie:
    """Windows with counts. Middle words are hashes, neighbours their codes."""

    PARTS = ("words", "near", "succ_at", "succ", "pred_at", "pred", "third_at", "third", "offset")
    CODES = ("a2", "a3", "b2", "b3")

    def __init__(self, parts: dict[str, EliasFano], codes: dict[str, np.ndarray]):
        self.parts, self.codes = parts, codes

    @classmethod
    def build(cls, words: np.ndarray, near: np.ndarray, m: np.ndarray, a: np.ndarray, b: np.ndarray, count: np.ndarray) -> "Trie":
        """Distinct windows in order, as positions in sorted ``words`` (m) and sorted ``near`` (a for w1, b for w3); all words occur."""
        m, size = m.astype(np.int64), max(1, len(near))
        succ, s = np.unique(m * size + b, return_inverse=True)
        pair = m * size + a
        new = np.diff(pair, prepend=-1) != 0
        pred, p = pair[new], np.cumsum(new) - 1
        edge = np.arange(len(words) + 1)
        succ_at, pred_at = np.searchsorted(succ // size, edge), np.searchsorted(pred // size, edge)
        width = np.diff(succ_at)[pred // size] if len(pred) else np.zeros(0, np.int64)
        offset = np.cumsum(width) - width
        third = offset[p] + s - succ_at[m] if len(m) else np.zeros(0, np.int64)
        third_at = np.append(np.flatnonzero(new), len(m))
        own = np.repeat(np.arange(len(words)), np.diff(succ_at))
        c2 = np.bincount(s, count, len(succ))
        a2, b2 = _smoothed(c2, np.bincount(own, c2, len(words)), np.diff(succ_at), own)
        a3, b3 = _smoothed(count, np.bincount(p, count, len(pred)), np.diff(third_at), p)
        values = {"words": words, "near": near, "succ_at": succ_at, "succ": succ, "pred_at": pred_at, "pred": pred, "third_at": third_at, "third": third, "offset": offset}
        return cls({k: EliasFano.of(values[k]) for k in cls.PARTS}, {"a2": a2, "a3": a3, "b2": b2, "b3": b3})

    def to_bytes(self) -> bytes:
        out = [self.parts[k].to_bytes() for k in self.PARTS]
        return b"".join(out + [struct.pack("<Q", len(self.codes[k])) + self.codes[k].tobytes() for k in self.CODES])

    @classmethod
    def view(cls, data) -> "Trie":
        """A trie in bytes that stay where they are: a binary value or a memory map."""
        at, parts, codes = 0, {}, {}
        for k in cls.PARTS:
            parts[k], at = EliasFano.view(data, at)
        for k in cls.CODES:
            (n,) = struct.unpack_from("<Q", data, at)
            codes[k] = np.frombuffer(data, "<u2", n, at + 8)
            at += 8 + 2 * n
        return cls(parts, codes)

    def mapped(self) -> "Trie":
        """The same in a memory map, from which it is read."""
        data = self.to_bytes()
        held = mmap.mmap(-1, max(1, len(data)))
        held.write(data)
        return Trie.view(held)

    def lookup(self, w1: int, w2: int, w3: int) -> tuple[int, int, int, int]:
        """Codes (a3, b3, a2, b2) of one window, by successor searches one element at a time."""
        g, nothing = self.parts, (NOTHING, 0, NOTHING, 0)

        def position(k: str, value: int, begin: int, end: int) -> int:
            i = g[k].find(value, begin, end)
            return i if i < end and g[k][i] == value else -1

        m = position("words", w2, 0, g["words"].n)
        if m < 0:
            return nothing
        size, first, last = g["near"].n, g["succ_at"][m], g["succ_at"][m + 1]
        x, y = (position("near", w, 0, size) for w in (w3, w1))
        s = position("succ", m * size + x, first, last) if x >= 0 else -1
        p = position("pred", m * size + y, g["pred_at"][m], g["pred_at"][m + 1]) if y >= 0 else -1
        t = position("third", g["offset"][p] + s - first, g["third_at"][p], g["third_at"][p + 1]) if s >= 0 and p >= 0 else -1
        code = lambda k, i, other: int(self.codes[k][i]) if i >= 0 else other
        return code("a3", t, NOTHING), code("b3", p, 0), code("a2", s, NOTHING), code("b2", m, 0)

    def answer(self, words: np.ndarray, near: np.ndarray, m: np.ndarray, a: np.ndarray, b: np.ndarray) -> dict[str, np.ndarray]:
        """Codes of windows that are distinct and in order, as positions in sorted ``words`` and ``near``: a3 and a2 by window, b3 by pair, b2 by word.

        The same searches as ``lookup``, level by level for all windows.
        """
        g = self.parts
        im, size = g["words"].locate(words), max(1, g["near"].n)
        ids = g["near"].locate(near)
        new = (np.diff(m, prepend=-1) != 0) | (np.diff(a, prepend=-1) != 0)
        mid, x, y = im[m], ids[b], ids[a[new]]
        key = lambda i, j: np.where((i >= 0) & (j >= 0), i * size + j, -1)
        s, p = g["succ"].locate(key(mid, x)), g["pred"].locate(key(mid[new], y))
        pair = p[np.cumsum(new) - 1] if len(m) else p
        both = np.flatnonzero((s >= 0) & (pair >= 0))
        t = np.full(len(m), -1, np.int64)
        t[both] = g["third"].locate(g["offset"].gather(pair[both]) + s[both] - g["succ_at"].gather(mid[both]))
        get = lambda k, i, other: np.where(i >= 0, self.codes[k][i], other).astype("<u2") if len(self.codes[k]) else np.full(len(i), other, "<u2")
        return {"a3": get("a3", t, NOTHING), "a2": get("a2", s, NOTHING), "b3": get("b3", p, 0), "b2": get("b2", im, 0)}


# ---------------------------------------------------------------- blocks


def _squeeze(*arrays: np.ndarray) -> bytes:
    """Arrays byte plane by byte plane, compressed."""
    head = struct.pack("<Q", len(arrays)) + b"".join(struct.pack("<2sQ", a.dtype.str[1:].encode(), len(a)) for a in arrays)
    planes = [np.ascontiguousarray(np.ascontiguousarray(a).view(np.uint8).reshape(len(a), -1).T).tobytes() if len(a) else b"" for a in arrays]
    return zstandard.ZstdCompressor(level=3).compress(head + b"".join(planes))


def _open(data: bytes) -> list[np.ndarray]:
    raw = zstandard.ZstdDecompressor().decompress(data)
    (n,) = struct.unpack_from("<Q", raw, 0)
    at, out, kinds = 8, [], []
    for _ in range(n):
        kinds.append(struct.unpack_from("<2sQ", raw, at))
        at += struct.calcsize("<2sQ")
    for kind, size in kinds:
        dtype = np.dtype("<" + kind.decode())
        planes = np.frombuffer(raw, np.uint8, size * dtype.itemsize, at).reshape(dtype.itemsize, size)
        out.append(np.ascontiguousarray(planes.T).view(dtype)[:, 0] if size else np.zeros(0, dtype))
        at += size * dtype.itemsize
    return out


def _gaps(x: np.ndarray) -> np.ndarray:
    """A sorted list as its differences."""
    return np.diff(x, prepend=x.dtype.type(0))


def _fit(x: np.ndarray) -> np.ndarray:
    """The narrowest unsigned form."""
    top = int(x.max()) if len(x) else 0
    return x.astype("<u1" if top < 256 else "<u2" if top < 65536 else "<u4")


def _mix(a: np.ndarray | int, b: np.ndarray) -> np.ndarray:
    """One hash of two."""
    h = np.atleast_1d(np.asarray(a, np.uint64)) * np.uint64(0x9E3779B97F4A7C15) ^ (b + np.uint64(0x632BE59BD9B4E019))
    h = (h ^ h >> np.uint64(31)) * np.uint64(0xBF58476D1CE4E5B9)
    return h ^ h >> np.uint64(29)


def _among(names: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Positions in sorted ``names``, -1 for what is not there."""
    if not len(names):
        return np.full(len(x), -1, np.int64)
    i = np.minimum(np.searchsorted(names, x), len(names) - 1)
    return np.where(names[i] == x, i, -1)


def _encode(block_chars: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number = TaskContext.get().partitionId() << 32
        for batch in batches:
            texts = pc.fill_null(batch.column("text"), "")
            for a, b in slices(pc.utf8_length(texts).to_pylist(), block_chars):
                lists = pc.ascii_split_whitespace(pc.ascii_lower(texts.slice(a, b - a)))
                each = pc.list_value_length(lists).to_numpy().astype(np.int64)
                flat = lists.flatten()
                real = pc.not_equal(flat, "").to_numpy(zero_copy_only=False)
                doc = np.repeat(np.arange(b - a), each)[real]
                coded = flat.filter(pa.array(real)).dictionary_encode()
                words = np.fromiter(map(xxhash.xxh64_intdigest, coded.dictionary.to_pylist()), np.uint64, len(coded.dictionary))
                n = np.bincount(doc, minlength=b - a)
                tokens = np.insert(coded.indices.to_numpy().astype(np.int64) + 1, np.cumsum(n), 0)
                held = batch.column("held").slice(a, b - a)
                train = np.repeat(~held.to_numpy(zero_copy_only=False), n + 1)
                counts = np.bincount(tokens[train], minlength=len(words) + 1)
                others = np.bincount(tokens, minlength=len(words) + 1) - counts
                words = np.maximum(words >> np.uint64(2), np.uint64(4))  # below 2**62, apart from the marks
                yield pa.RecordBatch.from_pydict({"block": pa.array([number], pa.int64()), "doc_ids": pa.array([batch.column("id").slice(a, b - a).to_pylist()], pa.list_(pa.int64())), "held": pa.array([held.to_pylist()], pa.list_(pa.bool_())), "n_windows": pa.array([len(tokens)], pa.int64()), "n_train": pa.array([int(train.sum())], pa.int64()), "n_train_docs": pa.array([int(counts[0])], pa.int64()), "words": pa.array([_squeeze(words.astype("<u8"), _fit(counts[1:]), _fit(others[1:]))], pa.binary()), "tokens": pa.array([_squeeze(_fit(tokens), (n + 1).astype("<u4"))], pa.binary())})
                number += 1

    return run


BLOCK = "block long, doc_ids array<long>, held array<boolean>, n_windows long, n_train long, n_train_docs long, words binary, tokens binary"


@dataclass
class Plan:
    """How windows are dealt: numbers of shards for cold words, hot words by pair, and split contexts; hot words and hot pairs as sorted hashes."""

    cold: int = 1
    by_pair: int = 0
    split: int = 0
    words: np.ndarray = field(default_factory=lambda: np.zeros(0, np.uint64))
    pairs: np.ndarray = field(default_factory=lambda: np.zeros(0, np.uint64))

    def kind(self, place: int) -> int:
        return 0 if place < self.cold else 1 if place < self.cold + self.by_pair else 2


class Windows:
    """The windows of a block. Local ids: 0 the begin or the end, then words in the order of their hashes, then any word."""

    def __init__(self, words: bytes, tokens: bytes, held: list[bool], plan: Plan):
        self.words, self.plan = _open(words)[0], plan
        self.tokens, self.each = _open(tokens)
        order = np.argsort(self.words)  # ids in the order of hashes, so that lists of either are sorted
        rank = np.zeros(len(order) + 1, np.int32)
        rank[order + 1] = np.arange(1, len(order) + 1)
        self.words, self.tokens, self.each = self.words[order], rank[self.tokens], self.each.astype(np.int64)
        first = np.zeros(len(self.tokens), bool)
        first[np.cumsum(self.each) - self.each] = True
        none = np.zeros(2, np.int32)
        self.w2 = np.concatenate([none[:1], self.tokens[:-1]])
        self.w1 = np.concatenate([none, self.tokens[:-2]])[: len(self.tokens)]
        self.w2[first] = 0
        self.w1[first] = 0
        self.w1[np.flatnonzero(first[:-1]) + 1] = 0
        self.any = len(self.words) + 1
        self.middle = np.concatenate([[np.uint64(BEGIN)], self.words, [np.uint64(ANY)]])
        # Neighbours by local number: the begin, the end, words, any word. They are as sorted as the local ids.
        self.near = np.concatenate([np.array([NEAR_BEGIN, NEAR_END], np.uint64), np.maximum(self.words >> NEAR_SHIFT, np.uint64(NEAR_END + 1)), [np.uint64(NEAR_ANY)]])
        self.hot = _among(plan.words, self.middle) >= 0
        self.bits = (self.any + 1).bit_length()
        self.train = np.repeat(~np.array(held, bool), self.each)

    def keys(self) -> np.ndarray:
        """A number for each window, which sorts them by w2, w1, w3."""
        if 3 * self.bits > 61:
            raise ValueError("a block has too many words; make blocks smaller")
        keys = self.w2.astype(np.int64)
        for x in (self.w1, self.tokens):
            keys <<= self.bits
            keys |= x
        return keys

    def split(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(w2, w1, w3)."""
        mask = (1 << self.bits) - 1
        return (keys >> 2 * self.bits).astype(np.int32), (keys >> self.bits & mask).astype(np.int32), (keys & mask).astype(np.int32)

    def before(self, w1: np.ndarray) -> np.ndarray:
        """Local numbers of neighbours before a middle word."""
        return np.where(w1 == 0, 0, w1 + 1)

    def after(self, w3: np.ndarray) -> np.ndarray:
        return w3 + 1

    def hot_pairs(self, least: int) -> tuple[np.ndarray, np.ndarray]:
        """Contexts (w1, w2) of hot words with ``least`` windows here, and how many."""
        both = self.hot[self.w1] & self.hot[self.w2]
        pair, n = np.unique(self.w2[both].astype(np.int64) << self.bits | self.w1[both], return_counts=True)
        pair, n = pair[n >= least], n[n >= least]
        return _mix(self.near[self.before(pair & (1 << self.bits) - 1)], self.middle[pair >> self.bits]), n


@dataclass
class Dealt:
    """Distinct windows of a block, then those of any word before a hot one; ``order`` sorts them by place and key.

    ``hot`` are the windows of hot words and ``any_of`` the row that stands for any word before each.
    """

    keys: np.ndarray
    place: np.ndarray
    order: np.ndarray
    hot: np.ndarray
    any_of: np.ndarray
    context: np.ndarray


def _deal(w: Windows, keys: np.ndarray) -> Dealt:
    plan, (w2, w1, w3) = w.plan, w.split(keys)
    place = (w.middle % np.uint64(plan.cold)).astype(np.int32)[w2]
    hot = np.flatnonzero(w.hot[w2])
    if not len(hot):
        return Dealt(keys, place, np.argsort(place, kind="stable"), hot, hot, np.zeros(len(keys), np.uint64))
    wide, any_of = np.unique((w2[hot].astype(np.int64) << w.bits | w.any) << w.bits | w3[hot], return_inverse=True)
    first = plan.cold + plan.by_pair
    pair = _mix(w.near[w.before(w1[hot])], w.middle[w2[hot]])
    mine = (_mix(pair, w.near[w.after(w3[hot])]) % np.uint64(plan.split)).astype(np.int32) + first
    place[hot] = np.where(_among(plan.pairs, pair) >= 0, mine, (pair % np.uint64(plan.by_pair)).astype(np.int32) + plan.cold)
    v2, _, v3 = w.split(wide)
    every = _mix(NEAR_ANY, w.middle[v2])
    place = np.concatenate([place, (_mix(every, w.near[w.after(v3)]) % np.uint64(plan.split)).astype(np.int32) + first])
    context = np.zeros(len(place), np.uint64)
    context[hot], context[len(keys) :] = pair, every
    order = np.argsort(place, kind="stable")  # both lists are in the order of keys, and any word comes last
    keys = np.concatenate([keys, wide])
    mixed = np.flatnonzero(place[order] >= first)
    order[mixed] = order[mixed][np.lexsort((keys[order[mixed]], place[order[mixed]]))]
    return Dealt(keys, place, order, hot, any_of + len(w2), context)


def _runs(*sorted_by: np.ndarray) -> np.ndarray:
    """Where any of the columns changes."""
    new = np.zeros(len(sorted_by[0]), bool)
    for x in sorted_by:
        new |= np.diff(x, prepend=-1) != 0
    return new


def _asked(words: bytes, tokens: bytes, held: list[bool], plan: Plan) -> tuple[np.ndarray, list[bytes]]:
    """Places that a block asks, and what it asks each."""
    w = Windows(words, tokens, held, plan)
    keys = w.keys()
    del w.w1, w.w2, w.tokens
    keys <<= 1
    keys |= w.train
    both, n = np.unique(keys, return_counts=True)
    keys, at = np.unique(both >> 1, return_index=True)
    count = np.add.reduceat(np.where(both & 1, n, 0), at).astype(np.int32) if len(at) else n.astype(np.int32)
    del both, n, at
    d = _deal(w, keys)
    count = np.concatenate([count, np.bincount(d.any_of - len(keys), count[d.hot], len(d.keys) - len(keys)).astype(np.int32)])[d.order]
    place, (w2, w1, w3) = d.place[d.order], w.split(d.keys[d.order])
    del d, keys
    first, last = w.before(w1), w.after(w3)
    edges = np.append(np.flatnonzero(np.diff(place, prepend=-1)), len(place))
    payloads = []
    for a, b in zip(edges[:-1], edges[1:], strict=True):
        middle, run_of = np.unique(w2[a:b], return_counts=True)
        near = np.unique(np.concatenate([first[a:b], last[a:b]]))
        before = np.searchsorted(near, first[a:b])
        step = np.diff(before, prepend=0)  # grows within the run of a middle word
        begin = np.cumsum(run_of) - run_of
        step[begin] = before[begin]
        payloads.append(_squeeze(_gaps(w.middle[middle]), _fit(run_of), _gaps(w.near[near]), _fit(step), _fit(np.searchsorted(near, last[a:b])), _fit(count[a:b])))
    return place[edges[:-1]], payloads


def _requests(plan: Plan):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in range(batch.num_rows):
                places, payloads = _asked(batch.column("words")[r].as_py(), batch.column("tokens")[r].as_py(), batch.column("held")[r].as_py(), plan)
                yield pa.RecordBatch.from_pydict({"block": pa.array([batch.column("block")[r].as_py()] * len(payloads), pa.int64()), "place": pa.array(places, pa.int32()), "payload": pa.array(payloads, pa.binary())})
                del payloads
                tidy()

    return run


def _windows(p: list[np.ndarray], words: np.ndarray, near: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Middle word, word before and word after of a payload's windows, as positions in common lists."""
    run = p[1].astype(np.int64)
    begin = np.cumsum(run) - run
    step = np.cumsum(p[3].astype(np.int64))
    before = step - np.repeat(step[begin] - p[3][begin], run)
    return np.repeat(words, run).astype(np.int32), near[before].astype(np.int32), near[p[4]].astype(np.int32)


def _distinct(m: np.ndarray, a: np.ndarray, b: np.ndarray, words: int, near: int) -> tuple[np.ndarray, np.ndarray]:
    """The order of windows, and of each sorted one whether it is new."""
    if words * near * near < 1 << 62:
        key = (m.astype(np.int64) * near + a) * near + b
        order = np.argsort(key, kind="stable")
        return order, _runs(key[order])
    order = np.lexsort((b, a, m))
    return order, _runs(m[order], a[order], b[order])


def _answers(plan: Plan, keep_trie: bool):
    def of(held: pa.Table) -> pa.Table:
        kind = plan.kind(held.column("place")[0].as_py())
        parts = [_open(x) for x in held.column("payload").to_pylist()]
        for p in parts:
            p[0], p[2] = np.cumsum(p[0], dtype=np.uint64), np.cumsum(p[2], dtype=np.uint64)
        words, near = np.unique(np.concatenate([p[0] for p in parts])), np.unique(np.concatenate([p[2] for p in parts]))
        mine = [_windows(p, np.searchsorted(words, p[0]), np.searchsorted(near, p[2])) for p in parts]
        m, a, b = (np.concatenate([x[k] for x in mine]) for k in range(3))
        count = np.concatenate([p[5] for p in parts])
        parts = [(p[0], len(p[5])) for p in parts]
        del mine
        order, new = _distinct(m, a, b, len(words), len(near))
        which = np.empty(len(order), np.int32)
        which[order] = np.cumsum(new) - 1
        count = np.add.reduceat(count.astype(np.int64)[order], np.flatnonzero(new))
        m, a, b = (x[order[new]] for x in (m, a, b))
        del order, new
        pair = _runs(m, a)
        edges = np.cumsum([0] + [n for _, n in parts])
        out = {"payload": [], "n_words": 0, "totals": None, "trie": None}
        if kind == 2:
            out["payload"] = [_squeeze(_fit(count[which[x:y]])) for x, y in zip(edges[:-1], edges[1:], strict=True)]
            at = np.flatnonzero(pair)
            out["totals"] = _squeeze(_mix(near[a[at]], words[m[at]]), np.add.reduceat(count, at), np.add.reduceat((count > 0).astype(np.int64), at))
        else:
            some = count > 0
            use_m, use_n = np.unique(m[some]), np.unique(np.concatenate([a[some], b[some]]))
            trie = Trie.build(words[use_m].astype(np.int64), near[use_n].astype(np.int64), np.searchsorted(use_m, m[some]), np.searchsorted(use_n, a[some]), np.searchsorted(use_n, b[some]), count[some]).mapped()
            code = trie.answer(words.astype(np.int64), near.astype(np.int64), m, a, b)
            total = np.bincount(m, count, len(words)).astype(np.int64)
            if kind == 0:
                out["n_words"] = int(((total > 0) & (words != BEGIN)).sum())
            pair_of = np.cumsum(pair) - 1
            for (mine, _), x, y in zip(parts, edges[:-1], edges[1:], strict=True):
                at = which[x:y]
                by_pair = pair_of[at]
                codes = [code["a3"][at], code["b3"][by_pair[_runs(by_pair)]]]
                if kind == 0:
                    middle = np.searchsorted(words, mine)
                    codes += [code["a2"][at], code["b2"][middle], _fit(total[middle])]
                out["payload"].append(_squeeze(*codes))
            if keep_trie:
                out["trie"] = trie.to_bytes()
        rest = [None] * (len(parts) - 1)
        tidy()
        rows = {"block": held.column("block"), "place": held.column("place"), "payload": pa.array(out["payload"], pa.binary()), "n_words": pa.array([out["n_words"]] + [0] * len(rest), pa.int64()), "totals": pa.array([out["totals"], *rest], pa.binary())}
        return pa.table(rows | ({"trie": pa.array([out["trie"], *rest], pa.binary())} if keep_trie else {}))

    return of


def _scores(plan: Plan, totals: tuple[np.ndarray, np.ndarray, np.ndarray], n_train: int, n_words: int, end_count: int):
    denominator = float(n_train + n_words + 1)

    def split_codes(context: np.ndarray, count: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Values of successors and contexts whose totals are summed over shards."""
        i = _among(totals[0], context)
        total, kinds = (np.where(i >= 0, x[i], 0) if len(x) else np.zeros(len(i), np.int64) for x in totals[1:])
        a, b = _smoothed(count, total, kinds, np.arange(len(i)))
        return value_of(np.where(count > 0, a, NOTHING)), value_of(b)

    def score(w: Windows, answers: pa.Table) -> tuple[np.ndarray, np.ndarray]:
        """Log10 probability and training count of every token."""
        keys, inverse = np.unique(w.keys(), return_inverse=True)
        del w.w1, w.w2
        inverse = inverse.astype(np.int32)
        d = _deal(w, keys)
        place, (w2, w1, _) = d.place[d.order], w.split(d.keys[d.order])
        n = len(d.keys)
        a3, b3, a2, b2, raw = np.zeros(n), np.ones(n), np.zeros(n), np.ones(n), np.zeros(n, np.int64)
        count = np.zeros(w.any, np.int64)
        count[0] = end_count
        for s, payload in zip(answers.column("place").to_pylist(), answers.column("payload").to_pylist(), strict=True):
            x, y = np.searchsorted(place, [s, s + 1])
            got, kind, at = _open(payload), plan.kind(s), d.order[x:y]
            if kind == 2:
                raw[at] = got[0]
                continue
            a3[at], b3[at] = value_of(got[0]), value_of(got[1])[np.cumsum(_runs(w2[x:y], w1[x:y])) - 1]
            if kind == 0:
                run = np.cumsum(_runs(w2[x:y])) - 1
                a2[at], b2[at] = value_of(got[2]), value_of(got[3])[run]
                middle = np.unique(w2[x:y])
                count[middle[middle > 0]] = got[4][middle > 0]
        if len(d.hot):
            split = np.flatnonzero(d.place >= plan.cold + plan.by_pair)
            a, b = split_codes(d.context[split], raw[split])
            pairs = split < len(keys)
            a3[split[pairs]], b3[split[pairs]] = a[pairs], b[pairs]
            a2[split[~pairs]], b2[split[~pairs]] = a[~pairs], b[~pairs]
            a2[d.hot], b2[d.hot] = a2[d.any_of], b2[d.any_of]
        hot = np.flatnonzero(w.hot[1 : w.any]) + 1
        i = _among(totals[0], _mix(NEAR_ANY, w.middle[hot]))
        count[hot] = np.where(i >= 0, totals[1][i], 0) if len(totals[1]) else 0
        unigram = (count + 1.0) / denominator
        k = len(keys)
        p = a3[:k] + b3[:k] * (a2[:k] + b2[:k] * unigram[w.split(keys)[2]])
        return np.log10(p)[inverse], count[w.tokens]

    def of(blocks: pa.Table, answers: pa.Table) -> pa.Table:
        out = {k: [] for k in ("doc_id", "held_out", "n_tokens", "n_known", "base_score", "score")}
        for r in range(blocks.num_rows):
            held = blocks.column("held")[r].as_py()
            w = Windows(blocks.column("words")[r].as_py(), blocks.column("tokens")[r].as_py(), held, plan)
            each, count = score(w, answers)
            starts = np.cumsum(w.each) - w.each
            total_of = lambda x: np.add.reduceat(x, starts).tolist()
            out["doc_id"] += blocks.column("doc_ids")[r].as_py()
            out["held_out"] += held
            out["n_tokens"] += w.each.tolist()
            out["n_known"] += total_of((count > 0).astype(np.int64))
            out["base_score"] += total_of(np.log10((count + 1.0) / denominator))
            out["score"] += total_of(each)
            del w, each, count
            tidy()
        return pa.table({"doc_id": pa.array(out["doc_id"], pa.int64()), "held_out": pa.array(out["held_out"], pa.bool_()), "n_tokens": pa.array(out["n_tokens"], pa.int64()), "n_known": pa.array(out["n_known"], pa.int64()), "train_tokens": pa.array([n_train] * len(out["doc_id"]), pa.int64()), "base_score": pa.array(out["base_score"], pa.float64()), "score": pa.array(out["score"], pa.float64())})

    return of


def _frequent(share: float):
    """(name, n) of a block's middle words that have that share of its windows, two at least."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in range(batch.num_rows):
                words, train, others = _open(batch.column("words")[r].as_py())
                words, n = np.append(words, np.uint64(BEGIN)), np.append(train.astype(np.int64) + others, len(batch.column("doc_ids")[r].as_py()))
                many = n >= max(2, share * batch.column("n_windows")[r].as_py())
                yield pa.RecordBatch.from_pydict({"name": pa.array(words[many].view(np.int64), pa.int64()), "n": pa.array(n[many], pa.int64())})

    return run


def _frequent_pairs(plan: Plan, share: float):
    """(name, n) of a block's contexts of two hot words that have that share of its windows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in range(batch.num_rows):
                w = Windows(batch.column("words")[r].as_py(), batch.column("tokens")[r].as_py(), batch.column("held")[r].as_py(), plan)
                name, n = w.hot_pairs(max(2, share * len(w.tokens)))
                yield pa.RecordBatch.from_pydict({"name": pa.array(name.view(np.int64), pa.int64()), "n": pa.array(n, pa.int64())})

    return run


def _unpack_totals(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for x in batch.column("totals").to_pylist():
            name, total, kinds = _open(x)
            yield pa.RecordBatch.from_pydict({"name": pa.array(name.view(np.int64), pa.int64()), "total": pa.array(total, pa.int64()), "kinds": pa.array(kinds, pa.int64())})


def _plan(blocks: DataFrame, windows: int, shard_windows: int, hot: int) -> Plan:
    """Words and pairs with ``hot`` windows or more are hot; what is between a half of that and all of it may be either."""
    limit = max(hot, -(-windows // MOST_HOT))
    if windows <= limit:
        return Plan(cold=max(1, -(-windows // shard_windows)))
    share = limit / (2 * windows)
    frequent = lambda found: {r["name"]: r["n"] for r in found.groupBy("name").agg(F.sum("n").alias("n")).where(F.col("n") >= -(-limit // 2)).collect()}
    names = frequent(blocks.select("doc_ids", "n_windows", "words").mapInArrow(_frequent(share), "name long, n long"))
    if not names:
        return Plan(cold=max(1, -(-windows // shard_windows)))
    many = min(windows, sum(names.values()))
    shards = max(1, -(-many // shard_windows))
    plan = Plan(max(1, -(-(windows - many) // shard_windows)), shards, shards, np.sort(np.array(list(names), np.int64).view(np.uint64)))
    pairs = frequent(blocks.select("held", "words", "tokens").mapInArrow(_frequent_pairs(plan, share), "name long, n long"))
    plan.pairs = np.sort(np.array(list(pairs), np.int64).view(np.uint64))
    return plan


def train_and_score(docs: DataFrame, held: str = "held", id_col: str = "doc_id", text_col: str = "text", block_chars: int = 1 << 23, shard_windows: int = 1_000_000, hot: int = 1_000_000, keep_tries: bool = False) -> tuple[DataFrame, DataFrame]:
    """Scores of all documents by a model of those whose ``held`` column is false, and the table of answers.

    ``shard_windows`` and ``hot`` bound what meets in a task and change no score. With ``keep_tries`` the answers have
    each shard's trie.
    """
    d = docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(held), F.lit(False)).alias("held"), F.col(text_col).cast("string").alias("text"))
    blocks = materialise(d.mapInArrow(_encode(block_chars), BLOCK), "blocks")
    windows, n_train, ends = (x or 0 for x in blocks.agg(F.sum("n_windows"), F.sum("n_train"), F.sum("n_train_docs")).first())
    plan = _plan(blocks, windows, shard_windows, hot)
    asked = blocks.select("block", "held", "words", "tokens").mapInArrow(_requests(plan), "block long, place int, payload binary")
    schema = "block long, place int, payload binary, n_words long, totals binary" + (", trie binary" if keep_tries else "")
    answers = materialise(asked.groupBy("place").applyInArrow(_answers(plan, keep_tries), schema), "answers")
    n_words = (answers.agg(F.sum("n_words")).first()[0] or 0) + (ends > 0)
    totals = tuple(np.zeros(0, t) for t in (np.uint64, np.int64, np.int64))
    if plan.split:  # a row a split context, of which there are at most 2 * MOST_HOT
        got = answers.where("totals is not null").select("totals").mapInArrow(_unpack_totals, "name long, total long, kinds long").groupBy("name").agg(F.sum("total").alias("total"), F.sum("kinds").alias("kinds")).toArrow()
        name = got.column("name").to_numpy().view(np.uint64)
        order = np.argsort(name)
        totals = name[order], got.column("total").to_numpy()[order], got.column("kinds").to_numpy()[order]
        words = _among(totals[0], _mix(NEAR_ANY, plan.words[plan.words != BEGIN]))
        n_words += int((totals[1][words[words >= 0]] > 0).sum())
    result = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"
    scored = blocks.select("block", "doc_ids", "held", "words", "tokens").groupBy("block").cogroup(answers.select("block", "place", "payload").groupBy("block")).applyInArrow(_scores(plan, totals, n_train, n_words, ends), result)
    return scored, answers


def op1_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", (F.crc32(F.col("doc_id").cast("string")) % 7 == 2).alias("held"))
    return train_and_score(docs)[0]


QUERIES = {"op1_lm_scoring": op1_lm_scoring}
ORACLES: dict[str, str] = {}
