"""Measures: what a run costs and what it finds."""

from __future__ import annotations

import math
import time
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relseq.operators import refine, typemining
from relseq.operators.corpus import Corpus


def corpus_stats(corpus: Corpus) -> DataFrame:
    """One row: sequences, events, means and maxima, and events by type."""
    by_type = [F.sum(f"n_{t}").cast("long").alias(f"n_{t}") for t in corpus.types]
    return corpus.sequences.agg(F.count("*").alias("sequences"), F.sum("n_events").cast("long").alias("events"), F.round(F.avg("n_events"), 6).alias("mean_events"), F.max("n_events").alias("max_events"), F.sum("n_txn").cast("long").alias("transactions"), *by_type)


def length_histogram(corpus: Corpus) -> DataFrame:
    """(type, n_events, sequences), with ``all`` for every type together."""
    pairs = F.array(F.struct(F.lit("all").alias("type"), F.col("n_events").alias("n")), *[F.struct(F.lit(t).alias("type"), F.col(f"n_{t}").alias("n")) for t in corpus.types])
    return corpus.sequences.select(F.explode(pairs).alias("x")).groupBy("x.type", F.col("x.n").alias("n_events")).agg(F.count("*").alias("sequences"))


def specialised_share(found: DataFrame) -> DataFrame:
    """One row: patterns, specialised ones, and their share."""
    return found.agg(F.count("*").alias("patterns"), F.sum(F.col("specialised").cast("long")).alias("specialised"), F.round(F.avg(F.col("specialised").cast("double")), 6).alias("share"))


@dataclass
class Cell:
    """A setting of an experiment and what was measured."""

    workload: str
    scenario: str
    min_support: float
    max_gap: int | None = None
    max_span: int | None = None
    tenths: int = 10
    max_events: int | None = None
    patterns: int = 0
    skeletons: int = 0
    occurrences: int = 0
    specialised: float = 0.0
    stage1: float = 0.0
    stage2: float = 0.0


def run_cell(corpus: Corpus, cell: Cell) -> Cell:
    """Both stages, cold, timed separately."""
    t0 = time.perf_counter()
    mined = typemining.mine(corpus, cell.min_support, cell.max_gap, cell.max_span, cell.max_events)
    t1 = time.perf_counter()
    row = specialised_share(refine.to_patterns(mined, refine.refine(mined))).first()
    t2 = time.perf_counter()
    mined.rows.unpersist()
    cell.patterns, cell.specialised = row["patterns"], row["share"] or 0.0
    cell.skeletons, cell.occurrences = len(mined.skeletons), sum(n for _, n in mined.skeletons.values())
    cell.stage1, cell.stage2 = t1 - t0, t2 - t1
    return cell


def growth(sizes: list[float], values: list[float]) -> float:
    """Exponent of the power law that fits the values best: 1 is linear."""
    xs, ys = [math.log(s) for s in sizes], [math.log(max(v, 1e-9)) for v in values]
    mx, my = sum(xs) / len(xs), sum(ys) / len(ys)
    spread = sum((x - mx) ** 2 for x in xs)
    return sum((x - mx) * (y - my) for x, y in zip(xs, ys)) / spread if spread else 0.0


def peak_memory(spark) -> dict[str, dict[str, int]]:
    """Per executor: peak heap and execution memory, spilled and shuffled bytes so far, from the status store."""
    out: dict[str, dict[str, int]] = {}
    found = spark.sparkContext._jsc.sc().statusStore().executorList(False).iterator()
    while found.hasNext():
        e = found.next()
        own = {"disk": int(e.diskUsed()), "shuffle_read": int(e.totalShuffleRead()), "shuffle_write": int(e.totalShuffleWrite()), "max_memory": int(e.maxMemory())}
        peaks = e.peakMemoryMetrics()
        if peaks.isDefined():
            own |= {name: int(peaks.get().getMetricValue(name)) for name in ("JVMHeapMemory", "OnHeapExecutionMemory", "OnHeapStorageMemory")}
        out[e.id()] = own
    return out
