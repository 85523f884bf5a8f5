"""Language identification with hyperdimensional profiles.

Every letter symbol has a random vector of +1/-1. A trigram's vector binds (multiplies) its letters' vectors,
each rolled by its place; a text's vector bundles (adds) those of its trigrams; a language's prototype
bundles its training texts, each with weight one. Texts and prototypes are compared by cosine after the mean
prototype is taken from both. Bundling is linear, so prototypes are made from trigram sums per language and
only ``languages x DIM`` numbers reach the driver.

Defined results: null text, or text without letters, is ``und`` with score 0; ties go to the smaller label;
null labels teach nothing; without any training text all is ``und``; repeated rows are rows; empty table,
empty result; other columns are ignored.
"""

from __future__ import annotations

import sys
from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relseq.llm import store
from relseq.llm import text_kernels as tk

DIM = 512
SYMBOLS = 64
FOLDS = 5
SCALE = 10**9
BATCH = 256
CHUNK = 4096  # trigram vectors held at a time


@cache
def symbol_table() -> np.ndarray:
    """Code point -> symbol: 0 for no letter, 1-26 for a-z in either case, 27-63 dealt to all other letters."""
    out = np.zeros(sys.maxunicode + 1, np.uint8)
    for c in range(len(out)):
        ch = chr(c)
        if ch.isalpha():
            low = ord(ch.lower()[0])
            out[c] = low - 96 if 97 <= low <= 122 else 27 + (low * 2654435761 >> 7) % 37
    return out


@cache
def letters() -> np.ndarray:
    return (np.random.default_rng(20_24).integers(0, 2, (SYMBOLS, DIM)) * 2 - 1).astype(np.int8)


def gram_vectors(grams: np.ndarray) -> np.ndarray:
    """Bound vectors of trigram codes, one row each."""
    base = letters()
    first, second, third = np.roll(base, 2, axis=1), np.roll(base, 1, axis=1), base
    return (first[grams // SYMBOLS**2] * second[grams // SYMBOLS % SYMBOLS] * third[grams % SYMBOLS]).astype(np.float32)


def trigrams(data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Trigram codes of a slice of texts and the text each belongs to. A word's edge counts as one symbol 0."""
    table = symbol_table()
    points = np.frombuffer(data.tobytes().decode("utf-8", "replace").encode("utf-32-le"), np.uint32)
    heads = np.concatenate(([0], np.cumsum((data & 0xC0) != 0x80)))
    bounds = np.minimum(heads[off], len(points))
    symbols = table[points]
    owner = np.repeat(np.arange(len(off) - 1), np.diff(bounds))
    symbols, owner = symbols[: len(owner)], owner[: len(symbols)]
    # Each text is set between two edges, and runs of non-letters shrink to one.
    n = len(off) - 1
    order_owner = np.concatenate((owner, np.arange(n), np.arange(n)))
    place = np.concatenate((np.ones(len(owner), np.int8), np.zeros(n, np.int8), np.full(n, 2, np.int8)))
    order = np.argsort(order_owner.astype(np.int64) * 3 + place, kind="stable")
    symbols = np.concatenate((symbols, np.zeros(2 * n, symbols.dtype)))[order].astype(np.int32)
    owner = order_owner[order]
    keep = np.ones(len(symbols), bool)
    keep[1:] = (symbols[1:] != 0) | (symbols[:-1] != 0) | (owner[1:] != owner[:-1])
    symbols, owner = symbols[keep], owner[keep]
    if len(symbols) < 3:
        return np.zeros(0, np.int32), np.zeros(0, np.int64)
    codes = (symbols[:-2] * SYMBOLS + symbols[1:-1]) * SYMBOLS + symbols[2:]
    same = (owner[:-2] == owner[2:]) & (codes > 0)
    return codes[same], owner[2:][same]


def learn(docs: DataFrame, text_col: str = "text", lang_col: str = "lang") -> tuple[list[str], np.ndarray]:
    """Labels in order, and their centred prototypes followed by the mean (labels + 1 rows)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[str, np.ndarray] = {}
        count: dict[str, int] = {}
        for batch in batches:
            langs = batch.column(1).to_pylist()
            data, off = tk.buffers(batch.column(0))
            for lo, hi, part, cuts in tk.slices(data, off):
                codes, owner = trigrams(part, cuts)
                total = np.bincount(owner, minlength=hi - lo)
                weight = (1 / np.maximum(total, 1))[owner]
                names = langs[lo:hi]
                for lang in set(names):
                    mine = np.array([x == lang for x in names])
                    used = int((mine & (total > 0)).sum())
                    if used:
                        pick = mine[owner]
                        sums[lang] = sums.get(lang, 0) + np.bincount(codes[pick], weight[pick], SYMBOLS**3)
                        count[lang] = count.get(lang, 0) + used
        for lang, grams in sums.items():
            seen = np.flatnonzero(grams)
            vector = np.zeros(DIM)
            for at in range(0, len(seen), CHUNK):
                vector += grams[seen[at : at + CHUNK]] @ gram_vectors(seen[at : at + CHUNK])
            whole = np.rint(vector * SCALE / 1000).astype(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array([lang] * (DIM + 1)), pa.array(np.arange(DIM + 1, dtype=np.int32)), pa.array(np.append(whole, count[lang]))], ["lang", "dim", "value"])

    taught = docs.where(F.col(lang_col).isNotNull() & F.col(text_col).isNotNull()).select(F.col(text_col), F.col(lang_col).alias("lang"))
    found = taught.mapInArrow(run, "lang string, dim int, value long").groupBy("lang", "dim").agg(F.sum("value").alias("value")).collect()
    labels = sorted({r["lang"] for r in found})
    sums = np.zeros((len(labels), DIM + 1))
    for r in found:
        sums[labels.index(r["lang"]), r["dim"]] = r["value"]
    means = sums[:, :DIM] * 1000 / SCALE / np.maximum(sums[:, DIM:], 1)
    centre = means.mean(axis=0) if labels else np.zeros(DIM)
    return labels, np.vstack((means - centre, centre)).astype(np.float32)


def classify(docs: DataFrame, labels: list[str], model: np.ndarray, text_col: str = "text") -> DataFrame:
    """All columns but the text, with lang_pred and score (half of one plus the cosine)."""
    rest = [f for f in docs.schema.fields if f.name != text_col]
    lengths = np.linalg.norm(model[:-1], axis=1)
    profiles = (model[:-1] / np.where(lengths > 0, lengths, 1)[:, None]).T

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, off = tk.buffers(batch.column(len(rest)))
            best, score = np.full(batch.num_rows, -1), np.zeros(batch.num_rows)
            for lo, hi, part, cuts in tk.slices(data, off):
                codes, owner = trigrams(part, cuts)
                ends = np.searchsorted(owner, np.arange(hi - lo + 1))
                for a in range(0, hi - lo, BATCH):
                    b = min(a + BATCH, hi - lo)
                    own, grams = owner[ends[a] : ends[b]] - a, codes[ends[a] : ends[b]]
                    if not len(own) or not labels:
                        continue
                    present = np.zeros(SYMBOLS**3, np.int32)
                    present[grams] = 1
                    seen = np.flatnonzero(present)
                    present[seen] = np.arange(len(seen))
                    total = np.bincount(own, minlength=b - a)
                    bundle, place = np.zeros((b - a, DIM), np.float32), present[grams]
                    for at in range(0, len(seen), CHUNK):
                        some = seen[at : at + CHUNK]
                        mine = (place >= at) & (place < at + CHUNK)
                        counts = np.bincount(own[mine] * len(some) + place[mine] - at, minlength=(b - a) * len(some)).reshape(b - a, len(some))
                        bundle += counts.astype(np.float32) @ gram_vectors(some)
                    vectors = bundle / np.maximum(total, 1)[:, None] - model[-1]
                    size = np.linalg.norm(vectors, axis=1)
                    cosine = vectors @ profiles / np.where(size > 0, size, 1)[:, None]
                    top = cosine.argmax(axis=1)
                    known = total > 0
                    best[lo + a : lo + b][known] = top[known]
                    score[lo + a : lo + b][known] = np.clip((1 + cosine[np.arange(b - a), top]) / 2, 0, 1)[known]
            names = pa.array([labels[i] if i >= 0 else "und" for i in best], pa.string())
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(rest)], names, pa.array(score)], names=[*(f.name for f in rest), "lang_pred", "score"])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rest)
    return docs.select(*[f"`{f.name}`" for f in rest], text_col).mapInArrow(run, f"{schema}, lang_pred string, score double")


def op5_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = store.table(spark, sf_dir, "documents")
    held_out = F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % FOLDS == 0, F.lit(True)).alias("held_out")
    labels, model = learn(docs.where(~held_out))
    return classify(docs.select("doc_id", held_out, "text"), labels, model)
