"""Quality by ordinal cumulative-link regression on graded ratings.

P(grade <= j) = logistic(threshold_j - w.x) with one weight vector ``w`` over hashed text features and
ordered thresholds. A text's features are present or not: letter runs, their first four and five bytes, and
bands of a few shape measures (capitals, marks, immediate repeats, separators), so one bad word counts the
same in a short and in a long text. The fit uses at most ``SAMPLE`` labelled rows, chosen by a hash of the
id; scoring reads every text whole, with weights of a fixed size.

Grades of the given labels: 0 toxic, 1 low quality, 2 neither. Selected: P(grade >= 2) at least one half.

Defined results: null text scores as empty text; rows without a label or with a null grade are not learned
from; with no labelled rows everything has the top grade; with one grade present everything has that grade;
repeated rows are scored alike; other columns are kept by ``select_quality`` and ignored by ``score``.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relseq.llm import store
from relseq.llm import text_kernels as tk

BLOCK = 1 << 20
BITS = 18
SAMPLE = 12_000
LEAST_DOCS = 4
ROUNDS = 220
PENALTY = 5e-4
PREFIXES = (4, 5)
_PREFIX_SALT = tk.mix(np.arange(1, 16, dtype=np.uint64))


@dataclass(frozen=True)
class OrdinalModel:
    weights: np.ndarray
    thresholds: np.ndarray  # one fewer than grades

    def tails(self, eta: np.ndarray) -> np.ndarray:
        """P(grade >= j) for j = 1 .. grades - 1, a column each."""
        return 1 / (1 + np.exp(np.clip(self.thresholds[None, :] - eta[:, None], -50, 50)))


def features(data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct hashed features of a slice of texts, sorted by text: (text, feature)."""
    n = len(off) - 1
    found, bounds, starts = tk.letter_runs(data, off, PREFIXES)
    owner = np.repeat(np.arange(n), np.diff(bounds))
    keys = []
    for i, h in enumerate(found):
        real = h != 0
        keys.append((owner[real] << BITS) | ((h[real] ^ _PREFIX_SALT[i]) >> tk.U(64 - BITS)).astype(np.int64))

    def per_text(mask: np.ndarray) -> np.ndarray:
        total = np.concatenate(([0], np.cumsum(mask)))
        return (total[off[1:]] - total[off[:-1]]).astype(float)

    letters = np.maximum(per_text(tk.LETTER[data]), 1)
    size = np.maximum(off[1:] - off[:-1], 1)
    runs = np.maximum(np.diff(bounds), 1)
    whole = found[0]
    again = np.zeros(len(whole) + 1)
    if len(whole) > 1:
        again[2:] = np.cumsum((whole[1:] == whole[:-1]) & (owner[1:] == owner[:-1]))
    repeats = again[np.maximum(bounds[1:], 1)] - again[np.minimum(bounds[:-1] + 1, len(whole))]
    measures = [
        per_text((data >= 65) & (data < 91)) / letters,
        per_text(((data > 32) & (data < 48)) | ((data > 57) & (data < 65)) | ((data > 122) & (data < 127))) / size,
        np.maximum(repeats, 0) / runs,
        per_text(data == 124) / runs,
        per_text((data >= 48) & (data < 58)) / size,
        np.minimum(np.log2(size) / 20, 1),
    ]
    for i, m in enumerate(measures):
        band = np.minimum((np.sqrt(m) * 16).astype(np.int64), 15)
        # A text has its band's feature and those of all lower bands, so that a measure's effect can add up.
        text = np.repeat(np.arange(n), band + 1)
        below = np.arange(len(text)) - np.repeat(np.cumsum(band + 1) - band - 1, band + 1)
        keys.append((text << BITS) | (tk.mix((below + 100 * (i + 1)).astype(np.uint64)) >> tk.U(64 - BITS)).astype(np.int64))
    every = np.unique(np.concatenate(keys))
    return every >> BITS, every & ((1 << BITS) - 1)


def hashed(docs: DataFrame) -> DataFrame:
    """(grade, text) rows to (grade, features array)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, off = tk.buffers(batch.column(1))
            for lo, hi, part, cuts in tk.slices(data, off):
                owner, feature = features(part, cuts)
                ends = np.searchsorted(owner, np.arange(hi - lo + 1)).astype(np.int32)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo), pa.ListArray.from_arrays(pa.array(ends), pa.array(feature.astype(np.int32)))], ["grade", "features"])

    return docs.mapInArrow(run, "grade int, features array<int>")


def fit(grades: np.ndarray, feature: np.ndarray, ends: np.ndarray, levels: int, rounds: int = ROUNDS, penalty: float = PENALTY) -> OrdinalModel:
    """Adam on the penalised likelihood. ``ends``: row bounds into ``feature``."""
    n = len(grades)
    weights = np.zeros(1 << BITS)
    share = np.array([(grades >= j).mean() for j in range(1, levels)]) if n else np.ones(levels - 1)
    share = np.clip(share, 1e-4, 1 - 1e-4)
    first = -np.log(share / (1 - share))
    if n == 0 or len(np.unique(grades)) < 2:
        sure = int(grades[0]) if n else levels - 1
        return OrdinalModel(weights, np.where(np.arange(1, levels) <= sure, -20.0, 20.0))
    common = np.bincount(feature, minlength=1 << BITS) >= LEAST_DOCS
    used = np.flatnonzero(common)
    number = np.zeros(1 << BITS, np.int32)
    number[used] = np.arange(len(used))
    use = common[feature]
    column = number[feature[use]]
    before = np.cumsum(use, dtype=np.int32)
    cuts = np.concatenate(([0], before))[ends]
    del before, use
    # Rows are gone through in blocks of about so many features, which bounds what a round needs beside them.
    edges = [0, *(np.searchsorted(cuts, np.arange(BLOCK, cuts[-1], BLOCK)).tolist()), n]
    blocks = [(lo, hi) for lo, hi in zip(edges, edges[1:]) if lo < hi]
    size = np.diff(cuts)
    # Parameters: the used weights, the first threshold, logs of the steps between thresholds.
    params = np.concatenate((np.zeros(len(used)), first[:1], np.log(np.maximum(np.diff(first), 0.3))))
    m, v = np.zeros_like(params), np.zeros_like(params)
    k = len(used)
    low, high = grades - 1, grades  # thresholds around a grade, -1 and levels-1 being infinite
    for step in range(1, rounds + 1):
        steps = np.exp(params[k + 1 :])
        theta = params[k] + np.concatenate(([0], np.cumsum(steps)))
        eta = np.concatenate([np.bincount(np.repeat(np.arange(hi - lo), size[lo:hi]), params[column[cuts[lo] : cuts[hi]]], hi - lo) for lo, hi in blocks])
        cdf = 1 / (1 + np.exp(np.clip(eta[:, None] - theta[None, :], -40, 40)))
        full = np.hstack((np.zeros((n, 1)), cdf, np.ones((n, 1))))
        rows = np.arange(n)
        upper, lower = full[rows, high + 1], full[rows, low + 1]
        p = np.maximum(upper - lower, 1e-12)
        du, dl = upper * (1 - upper), lower * (1 - lower)
        slope = (du - dl) / p / n  # of the loss by eta
        g_theta = np.zeros(levels - 1)
        inner = high < levels - 1
        np.add.at(g_theta, high[inner], -(du / p / n)[inner])
        inner = low >= 0
        np.add.at(g_theta, low[inner], (dl / p / n)[inner])
        tail = np.cumsum(g_theta[::-1])[::-1]
        by_weight = penalty * params[:k]
        for lo, hi in blocks:
            by_weight += np.bincount(column[cuts[lo] : cuts[hi]], np.repeat(slope[lo:hi], size[lo:hi]), k)
        grad = np.concatenate((by_weight, tail[:1], tail[1:] * steps))
        m = 0.9 * m + 0.1 * grad
        v = 0.999 * v + 0.001 * grad * grad
        params = params - 0.05 * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)
    weights[used] = params[:k]
    return OrdinalModel(weights, params[k] + np.concatenate(([0], np.cumsum(np.exp(params[k + 1 :])))))


def train(docs: DataFrame, grades: DataFrame, levels: int = 3, sample: int = SAMPLE) -> OrdinalModel:
    """``docs(doc_id, text)`` and ``grades(doc_id, grade)``; at most ``sample`` rows are learned from."""
    chosen = grades.where("grade is not null and doc_id is not null").groupBy("doc_id").agg(F.min("grade").cast("int").alias("grade"))
    chosen = chosen.orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample)  # bounded by ``sample``, so it is broadcast
    # Repeated ids are one document, so ``sample`` bounds the rows that come to the driver.
    texts = docs.join(F.broadcast(chosen), "doc_id").groupBy("doc_id").agg(F.min("grade").alias("grade"), F.min(F.coalesce("text", F.lit(""))).alias("text"))
    rows = hashed(texts.select("grade", "text")).toArrow()
    if not rows.num_rows:
        return fit(np.zeros(0, int), np.zeros(0, int), np.zeros(1, int), levels)
    lists = rows.column("features").combine_chunks()
    return fit(rows.column("grade").to_numpy().astype(int), lists.values.to_numpy()[lists.offsets[0].as_py() :], lists.offsets.to_numpy() - lists.offsets[0].as_py(), levels)


def score(docs: DataFrame, model: OrdinalModel, text_col: str = "text") -> DataFrame:
    """Every column, with expected_grade and tail_prob (of the top grade)."""
    fields = docs.schema.fields
    place = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, off = tk.buffers(batch.column(place))
            eta = np.zeros(batch.num_rows)
            for lo, hi, part, cuts in tk.slices(data, off):
                owner, feature = features(part, cuts)
                eta[lo:hi] = np.bincount(owner, model.weights[feature], hi - lo)
            tails = model.tails(eta)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(tails.sum(axis=1)), pa.array(tails[:, -1])], names=[*batch.schema.names, "expected_grade", "tail_prob"])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in fields)
    return docs.mapInArrow(run, f"{schema}, expected_grade double, tail_prob double")


def label_grades(spark: SparkSession, sf_dir: str) -> DataFrame:
    toxic, fine = F.coalesce(F.col("toxic"), F.lit(0)) == 1, F.col("quality") == 1
    return store.table(spark, sf_dir, "labels").select("doc_id", F.when(toxic, 0).when(fine, 2).when(~fine, 1).alias("grade"))


def select_quality(docs: DataFrame, grades: DataFrame, least: float = 0.5) -> DataFrame:
    """The documents whose chance of the top grade is at least ``least``, columns as they came."""
    model = train(docs.select(F.col("doc_id"), F.col("text")), grades)
    inner = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.col("text").alias("text"))
    scored = score(inner, model)
    return scored.where(F.col("tail_prob") >= least).select(*[F.col("row").getField(c).alias(c) for c in docs.columns])


def op10_quality_ordinal(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = store.table(spark, sf_dir, "documents").select("doc_id", "text")
    model = train(docs, label_grades(spark, sf_dir))
    scored = score(docs, model).select("doc_id", "expected_grade", "tail_prob")
    return scored.withColumn("kept", F.col("tail_prob") >= 0.5)
