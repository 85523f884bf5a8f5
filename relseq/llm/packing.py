"""Best-fit packing of tokenised documents into fixed-length sequences.

Pieces above a third of the capacity go in first: at most two of them share a sequence, the largest taking
the largest partner that still fits. Smaller pieces then fill the tightest gap that holds them. Because
lengths are whole numbers up to the capacity, the plan is made on the *histogram of lengths* (at most
``capacity`` rows, whatever the input): sequences with equal contents so far are one range of numbers, and a
piece finds its place from its length and its rank among pieces of that length.

Defined results: null or empty text is one piece holding only the end mark; repeated rows are packed each;
other columns are ignored. Ids are those of the given vocabulary file, plus the end mark after each document.
"""

from __future__ import annotations

import re
import zlib
from bisect import bisect_left, insort
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from relseq.llm import store

CAPACITY = 2048
END_ID = 0
VOCABULARY = "word_bpe_49k.json"
PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"
ROWS_PER_RANK_GROUP = 500_000


class Cached(dict):
    """Id bytes by string, made on first use; the first ``limit`` strings, which hold the common ones, are kept."""

    def __init__(self, make, limit: int) -> None:
        super().__init__()
        self.make, self.limit = make, limit

    def __missing__(self, key: str) -> bytes:
        ids = self.make(key)
        if len(self) < self.limit:
            self[key] = ids
        return ids


class Encoder:
    """Text to id bytes. The vocabulary's word pattern never matches across white space, so plain Latin text
    is looked up chunk by chunk between spaces, and a new chunk word by word; any other text goes through the
    tokenizer whole."""

    #: The vocabulary file's word pattern (a fixed value), spelled for the standard module; below U+0250 it
    #: matches alike but for the marks that ODD lists.
    WORD = r"'s|'t|'re|'ve|'m|'ll|'d|[^\W\d_]+|\d|(?:[^\s\w]|_)+"
    #: Characters (or marks of special tokens) for which the short way is not taken.
    ODD = r"[^\x00-\x1b\x20-\x84\x86-\u024f\u2018-\u201e]|\u0130|<\|"
    ODD_ASCII = ("<|", "\x1c", "\x1d", "\x1e", "\x1f")

    def __init__(self, vocabulary: str = VOCABULARY) -> None:
        import os

        import public_tokenizers
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(vocabulary if os.path.isabs(vocabulary) else public_tokenizers.path(vocabulary))
        self.short = os.path.basename(vocabulary) == VOCABULARY  # the word pattern and lower-casing are that file's
        self.odd = re.compile(self.ODD).search
        split, words = re.compile(self.WORD).findall, Cached(self.whole, 600_000)
        self.chunks = Cached(lambda chunk: b"".join([words[w] for w in split(chunk)]), 300_000)

    def whole(self, text: str) -> bytes:
        return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, "<u4").tobytes()

    def __call__(self, text: str) -> bytes:
        if not self.short:
            return self.whole(text)
        if any(x in text for x in self.ODD_ASCII) if text.isascii() else self.odd(text):
            return self.whole(text)
        chunks = self.chunks
        return b"".join([chunks[w] for w in text.lower().split()])


_encoders: dict[str, Encoder] = {}


def encoder(vocabulary: str) -> Encoder:
    if vocabulary not in _encoders:
        _encoders[vocabulary] = Encoder(vocabulary)
    return _encoders[vocabulary]


def tokenised_pieces(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", capacity: int = CAPACITY, vocabulary: str = VOCABULARY) -> DataFrame:
    end = np.array([END_ID], "<u4").tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(vocabulary)
        for batch in batches:
            rows: list[tuple] = []
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                ids = memoryview(encode(text.as_py() or "") + end)
                for i, at in enumerate(range(0, len(ids), 4 * capacity)):
                    part = ids[at : at + 4 * capacity]
                    rows.append((doc, i, at // 4, len(part) // 4, zlib.crc32(part)))
            if rows:
                cols = list(zip(*rows))
                yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int32()), *(pa.array(c, pa.int64()) for c in cols[2:])], ["doc_id", "piece", "start", "length", "ids_crc32"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, PIECES)


def plan_packing(histogram: dict[int, int], capacity: int = CAPACITY) -> list[tuple[int, int, int, int, int, int]]:
    """Placements (length, rank_lo, rank_hi, first_sequence, per_sequence, offset) for a histogram of lengths.

    A placement puts the pieces of one length with ranks in [rank_lo, rank_hi) into consecutive sequences,
    ``per_sequence`` each, beginning at ``offset``.
    """
    placed: list[tuple[int, int, int, int, int, int]] = []
    gaps: list[int] = []  # sorted distinct gaps with open sequences
    open_by_gap: dict[int, list[tuple[int, int]]] = {}  # gap -> ranges (first sequence, count)
    ranks = dict.fromkeys(histogram, 0)
    fresh = 0

    def add(gap: int, first: int, count: int) -> None:
        if gap > 0 and count > 0:
            if gap not in open_by_gap:
                open_by_gap[gap] = []
                insort(gaps, gap)
            open_by_gap[gap].append((first, count))

    def put(length: int, todo: int, first: int, count: int, gap: int, per: int) -> int:
        """Fill sequences first .. first+count with up to per pieces each; returns how many pieces went in."""
        at = capacity - gap
        full, some = divmod(min(todo, per * count), per)
        for n, seqs, begin in ((per, full, first), (some, 1 if some else 0, first + full)):
            if n and seqs:
                lo = ranks[length]
                ranks[length] = lo + n * seqs
                placed.append((length, lo, lo + n * seqs, begin, n, at))
                add(gap - n * length, begin, seqs)
        used = full + (1 if some else 0)
        add(gap, first + used, count - used)
        return full * per + some

    def take(gap: int) -> tuple[int, int]:
        ranges = open_by_gap[gap]
        out = ranges.pop()
        if not ranges:
            del open_by_gap[gap]
            gaps.remove(gap)
        return out

    large = {s: c for s, c in histogram.items() if 3 * s > capacity and c}
    waiting = dict(large)
    order = sorted(large)
    for s in reversed(order):  # the largest takes the largest partner that fits
        while waiting[s]:
            i = bisect_left(order, capacity - s + 1) - 1
            while i >= 0 and (not waiting[order[i]] or order[i] > s):
                i -= 1
            if i < 0:
                todo, waiting[s] = waiting[s], 0
                put(s, todo, fresh, todo, capacity, 1)
                fresh += todo
                continue
            t = order[i]
            n = waiting[s] // 2 if t == s else min(waiting[s], waiting[t])
            if n == 0:  # one left of this length, and it is its own best partner: look further down
                j = i - 1
                while j >= 0 and not waiting[order[j]]:
                    j -= 1
                if j < 0:
                    waiting[s] = 0
                    put(s, 1, fresh, 1, capacity, 1)
                    fresh += 1
                    continue
                t, n = order[j], 1
            waiting[s] -= n
            waiting[t] -= n
            placed.append((s, ranks[s], ranks[s] + n, fresh, 1, 0))
            ranks[s] += n
            placed.append((t, ranks[t], ranks[t] + n, fresh, 1, s))
            ranks[t] += n
            add(capacity - s - t, fresh, n)
            fresh += n
    for s in sorted((s for s in histogram if 3 * s <= capacity), reverse=True):
        todo = histogram[s]
        while todo:
            i = bisect_left(gaps, s)
            if i == len(gaps):
                count = -(-todo // (capacity // s))
                todo -= put(s, todo, fresh, count, capacity, capacity // s)
                fresh += count
            else:
                gap = gaps[i]
                first, count = take(gap)
                todo -= put(s, todo, first, count, gap, gap // s)
    return placed


def pack(pieces: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """``pieces(doc_id, piece, length, ...)`` -> the same with sequence_id and offset. Read twice: pass a stored table."""
    spark = pieces.sparkSession
    histogram = {r["length"]: r["n"] for r in pieces.groupBy("length").agg(F.count("*").alias("n")).collect()}  # at most capacity rows
    groups = 1 + sum(histogram.values()) // ROWS_PER_RANK_GROUP
    by_length: dict[int, list[tuple]] = {}
    for length, *rest in plan_packing(histogram, capacity):
        by_length.setdefault(length, []).append(tuple(rest))
    plan = spark.createDataFrame(list(by_length.items()), "length long, places array<struct<lo: long, hi: long, first: long, per: long, at: long>>")

    dealt = pieces.withColumn("__g", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(groups)).cast("int"))
    within = Window.partitionBy("length", "__g").orderBy("doc_id", "piece", *(["ids_crc32"] if "ids_crc32" in pieces.columns else []))
    counts = dealt.groupBy("length", "__g").agg(F.count("*").alias("n"))
    base = counts.withColumn("base", F.coalesce(F.sum("n").over(Window.partitionBy("length").orderBy("__g").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("n")
    ranked = dealt.withColumn("rank", F.row_number().over(within).cast("long") - 1)
    if groups > 1:
        ranked = ranked.join(base, ["length", "__g"]).withColumn("rank", F.col("rank") + F.col("base")).drop("base")
    # The plan has a row for each length: at most ``capacity`` of them, so it is broadcast.
    ranked = ranked.join(F.broadcast(plan), "length")
    place = F.filter("places", lambda p: (p["lo"] <= F.col("rank")) & (F.col("rank") < p["hi"]))[0]
    ranked = ranked.withColumn("p", place).withColumn("k", F.col("rank") - F.col("p.lo"))
    return ranked.select(*pieces.columns, (F.col("p.first") + F.expr("k div p.per")).alias("sequence_id"), (F.col("p.at") + (F.col("k") % F.col("p.per")) * F.col("length")).alias("offset"))


def best_fit_pack(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", capacity: int = CAPACITY, vocabulary: str = VOCABULARY) -> DataFrame:
    return pack(store.materialise(tokenised_pieces(docs, id_col, text_col, capacity, vocabulary), "pieces"), capacity)


def op9_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return best_fit_pack(store.table(spark, sf_dir, "documents"))
