"""Token ids in Re-Pair compressed shards with random access.

Documents are range-partitioned by id and sorted, each task encodes its documents in order and cuts the ids into
shards of about ``shard_tokens``; a shard is one row of a Parquet table in the shared folder, so writing survives
lost executors and works on any store that Spark reaches. In a shard, rounds of Re-Pair replace frequent pairs of
ids by nonterminals until no pair occurs ``least`` times without overlap. A round counts exactly all pairs that can
reach its threshold, which falls from round to round: occurrences are first counted by a hash, which leaves few to sort.
Where chosen pairs overlap, the more frequent one is replaced and the other is left to the next round; of a run of one
id every other pair is taken. Once the threshold is ``least``, a round looks only at pairs that are new or were left.
The shard stores rules, sequence and the decoded offset of every 1024th symbol, by which any range of
ids is decoded without the rest. Symbols have as many bits as the largest needs.

The encoder sees a text as chunks between blanks and newlines, which no token of the tokenizer crosses, and keeps
the ids of chunks it has seen in a bounded cache.

Null text: only the end id. Very long texts are encoded whole. Null ids come first. Rows with one id are ordered by text hash. Empty table: no rows.
Other columns are not read.
"""

from __future__ import annotations

import os
import struct
import zlib
from collections.abc import Iterator
from itertools import chain, repeat

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import materialise, slices, table, tidy

END = 2
SAMPLE = 1024
#: Bits of the hash that pairs are first counted by, and what the threshold is divided by from round to round.
SLOT_BITS, FALL = 20, 4
#: Expansions of at most so many ids are kept in a table; longer ones are split when they are met.
SHORT = 64
#: A Latin word and ASCII marks behind it, which encode alike apart (an apostrophe may begin a suffix, so it is no such mark), and characters that may stand between chunks if the tokenizer has an id for one.
WORD = r"^(?P<stem>[A-Za-z\x{C0}-\x{D6}\x{D8}-\x{F6}\x{F8}-\x{12F}\x{131}-\x{24F}]+)(?P<tail>[.,!?;:#*&%$|+=/()\[\]{}<>@^~_-]*)$"
MARKS = ["\u2603", "\u2693", "\u2622", "\u266b", "\u2665", "\u00a9"]
_encoders: dict[str, "ChunkEncoder"] = {}


class ChunkEncoder:
    def __init__(self, path: str, most: int = 200_000):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer, self.most = Tokenizer.from_file(path), most
        known = [(c, e.ids[0]) for c, e in zip(MARKS, self.tokenizer.encode_batch(MARKS, add_special_tokens=False), strict=True) if len(e.ids) == 1]
        self.mark = known[0] if known else None
        vocabulary = self.tokenizer.get_vocab()
        self.ends = np.zeros(max(vocabulary.values()) + 1, bool)
        self.ends[[i for t, i in vocabulary.items() if t.endswith("</w>")]] = True
        self.light = self._without_normaliser()
        self._clear()

    def _without_normaliser(self):
        """The same model, not a copy, behind blanks alone: plain words need no normalising and no splitting."""
        from tokenizers import Tokenizer, pre_tokenizers

        if not self.ends.any() or "ByteLevel" not in repr(self.tokenizer.pre_tokenizer):
            return None
        if hasattr(model := self.tokenizer.model, "_resize_cache"):  # it hardly sees a chunk twice
            model._resize_cache(0)
        light = Tokenizer(model)
        light.pre_tokenizer = pre_tokenizers.Sequence([pre_tokenizers.WhitespaceSplit(), pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)])
        return light

    def _clear(self) -> None:
        self.atoms: dict[str, int] = {}
        self.start, self.length, self.flat, self.used = np.zeros(1024, np.int64), np.zeros(1024, np.int64), np.zeros(4096, np.uint32), 0

    def _together(self, chunks: list[str]) -> tuple[np.ndarray, np.ndarray] | None:
        """Encode all chunks as one text with a mark between them, where the mark cannot be mistaken."""
        text = f" {self.mark[0]} ".join(chunks)
        if text.count(self.mark[0]) != len(chunks) - 1:
            return None
        ids = np.array(self.tokenizer.encode_batch_fast([text], add_special_tokens=False)[0].ids, np.uint32)
        at = np.flatnonzero(ids == self.mark[1])
        if len(at) != len(chunks) - 1:
            return None
        return np.delete(ids, at), np.diff(np.concatenate([[-1], at, [len(ids)]])) - 1

    def _words(self, chunks: list[str]) -> tuple[np.ndarray, np.ndarray] | None:
        """Encode plain words as one text; the last id of a word is one that ends words."""
        ids_of = lambda t, some: t.encode_batch_fast([" ".join(some)], add_special_tokens=False)[0].ids
        some = chunks[:: max(1, len(chunks) // 32)]
        if self.light and ids_of(self.light, some) != ids_of(self.tokenizer, some):  # of every run, some go through both
            self.light = None
        ids = np.array(ids_of(self.light or self.tokenizer, chunks), np.uint32)
        at = np.flatnonzero(self.ends[ids])
        return (ids, np.diff(at, prepend=-1)) if len(at) == len(chunks) and at[-1] == len(ids) - 1 else None

    def _encode_each(self, chunks: list[str]) -> tuple[np.ndarray, np.ndarray]:
        got = [e.ids for e in self.tokenizer.encode_batch_fast(chunks, add_special_tokens=False)]
        lens = np.fromiter(map(len, got), np.int64, len(got))
        return np.fromiter(chain.from_iterable(got), np.uint32, int(lens.sum())), lens

    def _learn(self, atoms: list[str]) -> None:
        plain = [x.isalpha() and (x.isascii() or max(x) < "\u0250") for x in atoms]
        words, rest = [x for x, p in zip(atoms, plain, strict=True) if p], [x for x, p in zip(atoms, plain, strict=True) if not p]
        atoms = words + rest
        cut = lambda xs: [xs[i : i + 4096] for i in range(0, len(xs), 4096)]
        got = [(self.ends.any() and self._words(run)) or self._encode_each(run) for run in cut(words)]
        got += [(self.mark and self._together(run)) or self._encode_each(run) for run in cut(rest)]
        n, ids, lens = len(self.atoms), np.concatenate([x for x, _ in got]), np.concatenate([x for _, x in got])
        while n + len(lens) > len(self.start):
            self.start, self.length = np.resize(self.start, 2 * len(self.start)), np.resize(self.length, 2 * len(self.length))
        while self.used + len(ids) > len(self.flat):
            self.flat = np.resize(self.flat, 2 * len(self.flat))
        self.flat[self.used : self.used + len(ids)] = ids
        self.length[n : n + len(lens)] = lens
        self.start[n : n + len(lens)] = self.used + np.cumsum(lens) - lens
        self.used += len(ids)
        self.atoms.update(zip(atoms, range(n, n + len(lens)), strict=True))

    def _atoms(self, values: pa.Array) -> np.ndarray:
        """Row numbers in the table of atoms."""
        coded = values.dictionary_encode()
        names = coded.dictionary.to_numpy(zero_copy_only=False).tolist()
        at = np.fromiter(map(self.atoms.get, names, repeat(-1)), np.int64, len(names))
        if len(missing := np.flatnonzero(at < 0)):
            new = [names[i] for i in missing.tolist()]
            self._learn(new)
            at[missing] = np.fromiter(map(self.atoms.__getitem__, new), np.int64, len(new))
        return at[coded.indices.to_numpy()]

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """All ids with the end id after each text, and the number of ids of each text."""
        if len(self.atoms) > self.most or self.used > 16 * self.most:
            self._clear()
        lists = pc.split_pattern(pc.replace_substring(pc.fill_null(texts, ""), "\n", " "), " ")
        per_text = pc.list_value_length(lists).to_numpy().astype(np.int64)
        coded = lists.flatten().dictionary_encode()
        chunks = coded.dictionary
        parts = pc.extract_regex(chunks, WORD)
        whole = parts.is_null()
        stem = pc.if_else(whole, chunks, pc.utf8_lower(pc.struct_field(parts, 0)))
        tail = pc.if_else(whole, "", pc.struct_field(parts, 1))
        pairs = np.stack([self._atoms(stem), self._atoms(tail)], 1) if len(chunks) else np.zeros((0, 2), np.int64)
        which = pairs[coded.indices.to_numpy()].ravel()
        lens = self.length[which].astype(np.int32)
        upto = np.concatenate([np.zeros(1, np.int32), np.cumsum(lens, dtype=np.int32)])
        total = int(upto[-1])
        at = np.repeat(self.start[which].astype(np.int32) - upto[:-1], lens)
        at += np.arange(total, dtype=np.int32)
        ids = self.flat[at] if total else np.zeros(0, np.uint32)
        ends = upto[2 * np.cumsum(per_text)]
        return np.insert(ids, ends, END).astype(np.uint32), np.diff(ends, prepend=0) + 1


def encoder(path: str) -> ChunkEncoder:
    """One encoder a Python worker. A task's function carries copies of the globals it names, so the cache is behind a function of this module."""
    if path not in _encoders:
        _encoders[path] = ChunkEncoder(path)
    return _encoders[path]


def _apart(seq: np.ndarray, same: np.ndarray) -> np.ndarray:
    """Whether a pair begins here; in a run of one symbol every other one does."""
    ok, at = np.ones(len(same), bool), np.flatnonzero(same)
    if len(at):
        new = np.diff(at, prepend=-2) > 1
        ok[at[(at - at[new][np.cumsum(new) - 1]) % 2 == 1]] = False
    return ok


def _slot(left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """A hash of pairs of 32-bit symbols, as positions in a table."""
    h = left.view(np.uint32) * np.uint32(0x9E3779B1)
    h += right.view(np.uint32)
    h *= np.uint32(0x85EBCA6B)
    h >>= np.uint32(32 - SLOT_BITS)
    return h.astype(np.intp)


def repair(ids: np.ndarray, least: int = 4, rounds: int = 100_000) -> tuple[np.ndarray, np.ndarray, int]:
    """Sequence, rules (left, right) and the id of the first nonterminal. ``rounds`` is a bound that raises."""
    base = int(ids.max()) + 1 if len(ids) else 0
    seq, rules, n, floor, live = ids.astype(np.int32), [np.zeros((0, 2), np.int64)], base, 0, None
    for _ in range(rounds):
        if len(seq) < 2 * least:
            break
        same = seq[:-1] == seq[1:]
        at = None if live is None else np.flatnonzero(live | same).astype(np.int32)
        if same.any():
            ok = _apart(seq, same)
            at = np.flatnonzero(ok).astype(np.int32) if at is None else at[ok[at]]
        left, right = (seq[:-1], seq[1:]) if at is None else (seq[at], seq[at + 1])
        slot = _slot(left, right)
        counts = np.bincount(slot, minlength=1 << SLOT_BITS)
        floor = max(least, (floor or int(counts.max())) // FALL)
        some = np.flatnonzero((counts >= floor)[slot])
        keys = left[some].astype(np.int64)
        keys <<= 32
        keys |= right[some]
        at, slot = some.astype(np.int32) if at is None else at[some], slot[some]
        del left, right, some
        pairs, times = np.unique(keys, return_counts=True)
        pairs, times = pairs[times >= floor], times[times >= floor]
        if not len(pairs):
            if floor == least:
                break
            continue
        order = np.argsort(-times, kind="stable")
        rank = np.empty(len(pairs), np.int32)
        rank[order] = np.arange(len(pairs))
        own = _slot((pairs >> 32).astype(np.int32), pairs.astype(np.int32))
        table = np.zeros(1 << SLOT_BITS, np.int32)
        table[own[order[::-1]]] = order[::-1]  # of pairs with one slot, the most frequent
        j = table[slot]
        hit = pairs[j] == keys
        if floor == least:  # what may be of a pair that lost its slot is looked at again
            shared = np.zeros(1 << SLOT_BITS, bool)
            shared[own[table[own] != np.arange(len(pairs))]] = True
            later = at[~hit & shared[slot]]
        at, mine = at[hit], rank[j[hit]]
        touch, more = at[1:] == at[:-1] + 1, mine[1:] < mine[:-1]
        won = np.ones(len(at), bool)
        won[1:] &= ~touch | more
        won[:-1] &= ~touch | (mine[:-1] < mine[1:])
        kept = np.bincount(mine[won], minlength=len(pairs)) >= least
        won &= kept[mine]
        name = (n + np.cumsum(kept) - 1).astype(np.int32)
        stay = np.ones(len(seq), bool)
        stay[at[won] + 1] = False
        seq[at[won]] = name[mine[won]]
        if floor == least:
            left = np.zeros(len(seq), bool)
            left[at[~won]] = left[later] = True
        seq = seq[stay]
        if floor == least:
            fresh = seq >= n
            live = (left[stay] | fresh)[:-1] | fresh[1:]
        best = pairs[order][kept]
        rules.append(np.stack([best >> 32, best & 0xFFFFFFFF], 1))
        n += len(best)
    else:
        raise RuntimeError("pairs are left after the last round")
    return seq, np.concatenate(rules).astype(np.int32), base


def _levels(rules: np.ndarray, base: int) -> Iterator[tuple[int, int]]:
    """Runs of rules whose sides are all older than the run."""
    newest, a = np.maximum.accumulate(rules.max(1)) if len(rules) else np.zeros(0), 0
    while a < len(rules):
        b = max(a + 1, int(np.searchsorted(newest, base + a)))
        yield a, b
        a = b


def _lengths(rules: np.ndarray, base: int) -> np.ndarray:
    """Ids that every symbol expands to."""
    lens = np.ones(base + len(rules), np.int64)
    for a, b in _levels(rules, base):
        lens[base + a : base + b] = lens[rules[a:b, 0]] + lens[rules[a:b, 1]]
    return lens


def _split(seq: np.ndarray, rules: np.ndarray, base: int, long: np.ndarray) -> np.ndarray:
    """``seq`` with symbols of ``long`` replaced by their two parts until none is left."""
    split = long[seq]
    if not split.any():
        return seq
    some = seq[split]
    owner = np.arange(len(some))
    while (two := long[some]).any():
        many = two + 1
        first = np.cumsum(many) - many
        out = np.repeat(some, many)
        out[first[two]] = rules[some[two] - base, 0]
        out[first[two] + 1] = rules[some[two] - base, 1]
        some, owner = out, np.repeat(owner, many)
    many = np.ones(len(seq), np.int64)
    many[split] = np.bincount(owner)
    out, split = np.repeat(seq, many), np.repeat(split, many)
    out[split] = some
    return out


def _planes(symbols: np.ndarray, bits: int) -> bytes:
    """The lower 16 bits of all symbols, then plane by plane the bits above."""
    return b"".join([symbols.astype("<u2").tobytes(), *[np.packbits((symbols >> k & 1).astype(np.uint8)).tobytes() for k in range(16, bits)]])


class _Planes:
    """Reader of symbols in planes."""

    def __init__(self, data: bytes, at: int, n: int, bits: int):
        self.n, self.low = n, np.frombuffer(data, "<u2", n, at)
        size = -(-n // 8)
        self.high = [np.frombuffer(data, np.uint8, size, at + 2 * n + k * size) for k in range(bits - 16)]
        self.end = at + 2 * n + size * len(self.high)

    def get(self, a: int, b: int) -> np.ndarray:
        """Symbols a..b; a is a multiple of 8."""
        b = min(b, self.n)
        out = self.low[a:b].astype(np.int64)
        for k, plane in enumerate(self.high):
            out |= np.unpackbits(plane[a // 8 : -(-b // 8)], count=max(b - a, 0)).astype(np.int64) << (16 + k)
        return out


MAGIC = b"RPR2"


def pack(ids: np.ndarray, least: int = 4) -> bytes:
    """magic, then ids, base, rules, symbols and bits as u64; samples (u64); left and right sides of the rules, and symbols, in planes."""
    seq, rules, base = repair(ids, least)
    lens = _lengths(rules, base)
    offsets = np.cumsum(lens[seq]) - lens[seq] if len(seq) else np.zeros(0, np.int64)
    bits = max(16, (base + len(rules)).bit_length())
    return b"".join([MAGIC, struct.pack("<5Q", len(ids), base, len(rules), len(seq), bits), offsets[::SAMPLE].astype("<u8").tobytes(), *[_planes(x, bits) for x in (rules[:, 0], rules[:, 1], seq)]])


class Shard:
    """Reader of a packed shard."""

    def __init__(self, data: bytes):
        if data[:4] != MAGIC:
            raise ValueError("not a packed shard")
        self.n, self.base, r, s, bits = struct.unpack_from("<5Q", data, 4)
        self.samples = np.frombuffer(data, "<u8", -(-s // SAMPLE), 44)
        left = _Planes(data, 44 + 8 * len(self.samples), r, bits)
        right = _Planes(data, left.end, r, bits)
        self.seq = _Planes(data, right.end, s, bits)
        self.rules = np.stack([left.get(0, r), right.get(0, r)], 1)
        lens = _lengths(self.rules, self.base)
        self.long = lens > SHORT
        self.length = np.where(self.long, 0, lens)
        self.start = np.cumsum(self.length) - self.length
        self.flat = np.empty(int(self.length.sum()), np.uint32)
        self.flat[: self.base] = np.arange(self.base)
        for a, b in _levels(self.rules, self.base):
            made = self._copied(self.rules[a:b][~self.long[self.base + a : self.base + b]].ravel())
            begin = int(self.start[self.base + a])
            self.flat[begin : begin + len(made)] = made

    def _expand(self, seq: np.ndarray) -> np.ndarray:
        return self._copied(_split(seq, self.rules, self.base, self.long))

    def _copied(self, seq: np.ndarray) -> np.ndarray:
        """Ids of symbols that are in the table."""
        lens = self.length[seq]
        total = int(lens.sum())
        return self.flat[np.repeat(self.start[seq] - (np.cumsum(lens) - lens), lens) + np.arange(total)]

    def ids(self) -> np.ndarray:
        return np.concatenate([self._expand(self.seq.get(i, i + (1 << 20))) for i in range(0, self.seq.n, 1 << 20)]) if self.seq.n else np.zeros(0, np.uint32)

    def range(self, a: int, b: int) -> np.ndarray:
        """Ids a..b, decoding only the symbols between two samples."""
        a, b = max(a, 0), min(b, self.n)
        if a >= b:
            return np.zeros(0, np.uint32)
        i = int(np.searchsorted(self.samples, a, "right")) - 1
        j = int(np.searchsorted(self.samples, b, "left"))
        part = self._expand(self.seq.get(i * SAMPLE, j * SAMPLE))
        return part[a - int(self.samples[i]) : b - int(self.samples[i])]


SHARD = "part int, chunk int, local_start long, n_ids long, doc_ids array<long>, n_tokens array<long>, payload binary"


def _writer(path: str, shard_tokens: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(path)
        part, chunk, begun, held, docs, lens = TaskContext.get().partitionId(), 0, 0, [], [], []

        def flush() -> pa.RecordBatch:
            nonlocal chunk, begun, held, docs, lens
            ids = np.concatenate(held)
            held.clear()
            row = pa.RecordBatch.from_pydict({"part": pa.array([part], pa.int32()), "chunk": pa.array([chunk], pa.int32()), "local_start": [begun], "n_ids": [len(ids)], "doc_ids": pa.array([docs], pa.list_(pa.int64())), "n_tokens": pa.array([lens], pa.list_(pa.int64())), "payload": pa.array([pack(ids)], pa.binary())})
            chunk, begun, held, docs, lens = chunk + 1, begun + len(ids), [], [], []
            return row

        for batch in batches:
            ids, texts = batch.column(0).to_pylist(), batch.column(1)
            sizes = pc.fill_null(pc.utf8_length(texts), 0).to_pylist()
            for a, b in slices(sizes, 1 << 21):
                flat, n = enc.encode(texts.slice(a, b - a))
                held.append(flat)
                docs += ids[a:b]
                lens += n.tolist()
                if sum(map(len, held)) >= shard_tokens:
                    yield flush()
        if docs:
            yield flush()
        tidy()

    return run


def write_tokens(docs: DataFrame, tokenizer_path: str, id_col: str = "doc_id", text_col: str = "text", shard_tokens: int = 1 << 21) -> DataFrame:
    """Write the shards to the shared folder; returns the table of shards read back."""
    d = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text")).withColumn("h", F.xxhash64("text"))
    ordered = d.repartitionByRange("id", "h").sortWithinPartitions("id", "h").select("id", "text")
    return materialise(ordered.mapInArrow(_writer(tokenizer_path, shard_tokens), SHARD), "tokens")


def _reader(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for row in range(batch.num_rows):
            docs, lens = batch.column("doc_ids")[row].as_py(), np.array(batch.column("n_tokens")[row].as_py(), np.int64)
            ids = Shard(batch.column("payload")[row].as_py()).ids().astype("<u4")
            ends = np.cumsum(lens)
            start = int(batch.column("offset")[row].as_py()) + int(batch.column("local_start")[row].as_py()) + ends - lens
            crc = [zlib.crc32(ids[b - n : b]) for b, n in zip(ends.tolist(), lens.tolist(), strict=True)]
            yield pa.RecordBatch.from_pydict({"doc_id": pa.array(docs, pa.int64()), "start": pa.array(start, pa.int64()), "n_tokens": pa.array(lens, pa.int64()), "ids_crc32": pa.array(crc, pa.int64())})


def read_digest(shards: DataFrame) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) decoded from the shards. What is broadcast has a row per writing task."""
    parts = shards.groupBy("part").agg(F.sum("n_ids").alias("n"))
    parts = parts.select("part", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).cast("long").alias("offset"))
    return shards.join(F.broadcast(parts), "part").select("offset", "local_start", "doc_ids", "n_tokens", "payload").mapInArrow(_reader, "doc_id long, start long, n_tokens long, ids_crc32 long")


def tokenizer_file(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op9_token_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_digest(write_tokens(table(spark, sf_dir, "documents"), tokenizer_file()))


QUERIES = {"op9_token_output": op9_token_output}
ORACLES: dict[str, str] = {}
