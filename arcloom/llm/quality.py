"""Quality classifier: ordinal cumulative-link regression on graded ratings.

Grades are ordered: 0 toxic, 1 poor, 2 good. One weight vector over hashed words and a few style shares moves a
document along the scale, ordered thresholds cut it: P(grade <= k) = sigmoid(t_k - w.x). That gives the expected
grade and the tail probability P(grade = best), by which documents are selected.

Fitting takes a bounded sample: the ``sample`` labelled documents with the smallest hash of their id, and of those as
many as have ``sample_bytes`` of features (documented parameters); a quarter, chosen by hash, is held out to set the cut so
that ``keep_good`` of good documents stay. The sample is put in the order of its hashes, so model and cut do not depend
on how the tables are laid out. Proximal gradient steps with an L1 penalty leave weights on telling words only.
Scoring is one scan of all whole texts, a few MB at a time.

Null or empty text: no words, scored by the thresholds alone. Very long texts are scored whole. Null labels are not
used. A document with several labels has its worst grade, one with several rows is learnt from all. Fewer than two grades in the sample: everything
is kept. Repeated rows get equal scores. Empty table: no rows. Other columns pass through untouched, whatever
their names, and are not read otherwise.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import TokenHasher, materialise, slices, table, tidy, unused

BITS = 18
#: Style shares: of tokens that are capitals, end in several marks, are a lone bar, or repeat the token before.
STYLE = ("capitals", "marks", "bars", "repeats")
CUTS = np.array([0.02, 0.1, 0.3, 0.6])
DENSE = len(STYLE) * (1 + len(CUTS))


class Features:
    def __init__(self, bits: int = BITS):
        self.hash, self.mask = TokenHasher(), np.uint64((1 << bits) - 1)

    def __call__(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Pairs (row, feature), each once, and the style features of each row."""
        lists = pc.utf8_split_whitespace(pc.fill_null(texts, ""))
        per_row = pc.list_value_length(lists).to_numpy().astype(np.int64)
        coded = lists.flatten().dictionary_encode()
        names, code = coded.dictionary, coded.indices.to_numpy()
        row = np.repeat(np.arange(len(texts)), per_row)
        stem = pc.utf8_lower(pc.replace_substring_regex(names, r"^[^\pL\pN]+|[^\pL\pN]+$", ""))
        feature = (self.hash(stem.to_pylist()) & self.mask).astype(np.int64)
        real = pc.not_equal(stem, "").to_numpy(zero_copy_only=False)
        pair = np.unique((row << 32 | feature[code])[real[code]])
        flag = np.stack([x.to_numpy(zero_copy_only=False) for x in (pc.and_(pc.utf8_is_upper(names), pc.greater(pc.utf8_length(names), 2)), pc.match_substring_regex(names, r"[^\pL\pN\s]{2,}$"), pc.equal(names, "|"))], 1).astype(float)
        hits = np.concatenate([flag[code], np.zeros((len(code), 1))], 1)
        if len(code) > 1:
            hits[1:, 3] = (code[1:] == code[:-1]) & (row[1:] == row[:-1])
        share = np.stack([np.bincount(row, hits[:, k], len(texts)) for k in range(4)], 1) / np.maximum(per_row, 1)[:, None]
        steps = (share[:, :, None] >= CUTS).reshape(len(texts), -1)
        return pair >> 32, pair & 0xFFFFFFFF, np.concatenate([share, steps.astype(float)], 1)


@dataclass
class OrdinalModel:
    weights: np.ndarray
    style: np.ndarray
    thresholds: np.ndarray
    cut: float = 0.0

    def margin(self, rows: np.ndarray, features: np.ndarray, style: np.ndarray) -> np.ndarray:
        return np.bincount(rows, self.weights[features], len(style)) + style @ self.style

    def at_most(self, margin: np.ndarray) -> np.ndarray:
        """P(grade <= k) for every k but the best."""
        return 1 / (1 + np.exp(-np.clip(self.thresholds[None, :] - margin[:, None], -40, 40)))

    def scores(self, margin: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        below = self.at_most(margin)
        return below.shape[1] - below.sum(1), 1 - below[:, -1]


def fit_ordinal(rows: np.ndarray, features: np.ndarray, style: np.ndarray, grade: np.ndarray, grades: int = 3, steps: int = 300, l1: float = 3e-4, least_docs: int = 5, width: int = 1 << BITS) -> OrdinalModel:
    """Accelerated proximal gradient on the mean negative log-likelihood."""
    n = len(grade)
    share = np.bincount(grade, minlength=grades) + 0.5
    below = np.cumsum(share)[:-1] / share.sum()
    t = np.log(below / (1 - below))
    model = OrdinalModel(np.zeros(width), np.zeros(style.shape[1]), t)
    if n == 0 or len(np.unique(grade)) < 2:
        return model
    common = np.bincount(features, minlength=width) >= least_docs
    held = common[features]
    rows, features = rows[held], features[held]
    names, cols = np.unique(features, return_inverse=True)
    size = np.bincount(rows, minlength=n) + style.sum(1) + 1
    bound = np.concatenate([np.bincount(cols, size[rows], len(names)), style.T @ size]) / n * 0.5 + 1e-9
    bound_t = 0.5 * size.mean()
    w, v, k = np.zeros(len(bound)), np.zeros(len(bound)), 1.0
    tv = t.copy()
    for _ in range(steps):
        m = np.bincount(rows, v[: len(names)][cols], n) + style @ v[len(names) :]
        edge = 1 / (1 + np.exp(-np.clip(np.concatenate([[-60.0], tv, [60.0]])[None, :] - m[:, None], -60, 60)))
        edge[:, 0], edge[:, -1] = 0, 1
        up, low = edge[np.arange(n), grade + 1], edge[np.arange(n), grade]
        p = np.maximum(up - low, 1e-12)
        slope = edge * (1 - edge)
        su, sl = slope[np.arange(n), grade + 1] / p, slope[np.arange(n), grade] / p
        g = (su - sl) / n
        grad = np.concatenate([np.bincount(cols, g[rows], len(names)), style.T @ g])
        gt = np.zeros(grades + 1)
        np.add.at(gt, grade + 1, -su / n)
        np.add.at(gt, grade, sl / n)
        new = v - grad / bound
        drop = l1 / bound[: len(names)]
        new[: len(names)] = np.sign(new[: len(names)]) * np.maximum(np.abs(new[: len(names)]) - drop, 0)
        nt = np.maximum.accumulate(tv - gt[1:-1] / bound_t * 4)
        nt[1:] = np.maximum(nt[1:], nt[:-1] + 1e-3)
        k2 = (1 + np.sqrt(1 + 4 * k * k)) / 2
        v, tv = new + (k - 1) / k2 * (new - w), nt
        w, t, k = new, nt, k2
    model.weights[names], model.style, model.thresholds = w[: len(names)], w[len(names) :], t
    return model


def _extract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    make = Features()
    for batch in batches:
        texts = batch.column("text")
        for a, b in slices(pc.fill_null(pc.utf8_length(texts), 0).to_pylist(), 1 << 21):
            rows, features, style = make(texts.slice(a, b - a))
            cut = np.searchsorted(rows, np.arange(b - a + 1))
            mine = [features[x:y].astype("<i4").tobytes() for x, y in zip(cut[:-1], cut[1:], strict=True)]
            yield pa.RecordBatch.from_pydict({"place": batch.column("place").slice(a, b - a), "id": batch.column("id").slice(a, b - a), "grade": batch.column("grade").slice(a, b - a), "features": pa.array(mine, pa.binary()), "style": pa.array([s.tobytes() for s in style], pa.binary())})


def train(docs: DataFrame, labels: DataFrame, sample: int = 12_000, sample_bytes: int = 1 << 28, keep_good: float = 0.999, id_col: str = "doc_id", text_col: str = "text") -> OrdinalModel:
    """``labels`` has (id, grade int). The sample's features, a few KB each, come to the driver."""
    chosen = labels.select(F.col(id_col).alias("id"), F.col("grade").cast("int").alias("grade")).where("id is not null and grade is not null").groupBy("id").agg(F.min("grade").alias("grade")).orderBy(F.xxhash64("id"), "id").limit(sample)
    d = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    marked = d.join(F.broadcast(chosen), "id").select(F.xxhash64("id").alias("place"), F.col("id").cast("string").alias("id"), "grade", "text")
    ordered = materialise(marked.mapInArrow(_extract, "place long, id string, grade int, features binary, style binary"), "sample").orderBy("place", "id", "features", "style")
    grade, each, style, fold, held = [], [], [], [], 0
    for r in ordered.toLocalIterator():
        held += len(r["features"]) + len(r["style"])
        if held > sample_bytes:
            break
        grade.append(r["grade"])
        each.append(np.frombuffer(r["features"], "<i4").astype(np.int64))
        style.append(np.frombuffer(r["style"]))
        fold.append(r["place"] // 7 % 4 == 3)
    grade, style, held_out = np.array(grade, np.int64), np.array(style).reshape(-1, DENSE), np.array(fold, bool)
    order = [np.flatnonzero(~held_out), np.flatnonzero(held_out)]
    flat = lambda ix: (np.repeat(np.arange(len(ix)), [len(each[i]) for i in ix]), np.concatenate([each[i] for i in ix]) if len(ix) else np.zeros(0, np.int64), style[ix])
    model = fit_ordinal(*flat(order[0]), grade[order[0]])
    best = model.scores(model.margin(*flat(order[1])))[1][grade[order[1]] == len(model.thresholds)]
    if len(np.unique(grade)) > 1 and len(best):
        model.cut = float(min(0.9, np.quantile(best, 1 - keep_good)))
    return model


def score_documents(docs: DataFrame, model: OrdinalModel, text_col: str = "text", out: str = "quality") -> DataFrame:
    """All columns of ``docs`` and a struct ``out`` (expected_grade, tail_prob, keep); a column of that name raises."""
    names = docs.columns
    if out in names:
        raise ValueError(f"the documents have a column {out}")
    shared = docs.sparkSession.sparkContext.broadcast(model)
    schema = T.StructType([*docs.schema.fields, T.StructField(out, T.StructType([T.StructField("expected_grade", T.DoubleType()), T.StructField("tail_prob", T.DoubleType()), T.StructField("keep", T.BooleanType())]))])
    at = names.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        make, m = Features(), shared.value
        for batch in batches:
            texts = batch.column(at)
            for a, b in slices(pc.fill_null(pc.utf8_length(texts), 0).to_pylist(), 1 << 21):
                part = batch.slice(a, b - a)
                expected, tail = m.scores(m.margin(*make(part.column(at))))
                quality = pa.StructArray.from_arrays([pa.array(expected), pa.array(tail), pa.array(tail >= m.cut)], ["expected_grade", "tail_prob", "keep"])
                yield pa.RecordBatch.from_arrays([*part.columns, quality], names=[*names, out])
        tidy()

    return docs.mapInArrow(run, schema)


def select_documents(docs: DataFrame, model: OrdinalModel, text_col: str = "text") -> DataFrame:
    """The documents that are kept, with their own columns."""
    out = unused(docs.columns, "quality")
    return score_documents(docs, model, text_col, out).where(F.col(out)["keep"]).drop(out)


def graded(labels: DataFrame) -> DataFrame:
    """Grade 0 for toxic, else 1 + quality; null where a label is."""
    return labels.select("doc_id", F.when(F.col("toxic") == 1, 0).when(F.col("toxic") == 0, F.when(F.col("quality").isin(0, 1), F.col("quality") + 1)).cast("int").alias("grade"))


def op10_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The selected documents, with expected grade and tail probability."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = train(docs, graded(table(spark, sf_dir, "labels")))
    return score_documents(docs, model).where("quality.keep").select("doc_id", "quality.expected_grade", "quality.tail_prob", "quality.keep")


QUERIES = {"op10_quality": op10_quality}
ORACLES: dict[str, str] = {}
