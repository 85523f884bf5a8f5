"""Plans: what a mining run will do, estimated from the length histogram before anything is matched."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import functions as F

from relseq.operators import patterns
from relseq.operators.corpus import Corpus
from relseq.operators.refine import GROUP_LIMIT


@dataclass
class Plan:
    sequences: int
    threshold: int
    bounds: dict[int, int]  # events of a skeleton -> bound of occurrences over all skeletons
    refine: str
    notes: list[str]

    def explain(self) -> str:
        lines = [f"{self.sequences} sequences, threshold {self.threshold}, refinement {self.refine}"]
        lines += [f"  {k} events: at most {n} occurrences" for k, n in self.bounds.items()]
        return "\n".join([*lines, *(f"  note: {n}" for n in self.notes)])


def plan(corpus: Corpus, min_support: float, max_gap: int | None = None, max_span: int | None = None, max_events: int = 3, budget: int = 10**10) -> Plan:
    """``budget``: occurrences above which the run is refused; tighten gap or span, or drop outliers first."""
    lengths = {r["n_events"]: r["n"] for r in corpus.sequences.groupBy("n_events").agg(F.count("*").alias("n")).collect()}  # one row a length
    total = sum(lengths.values())
    bounds = {k: sum(c * patterns.occurrence_bound(n, k, max_gap, max_span) for n, c in lengths.items() if n >= k) for k in range(1, max_events + 1)}
    notes = []
    longest = max(lengths, default=0)
    if max_gap is None and max_span is None and longest > 100:
        notes.append(f"the longest sequence has {longest} events and neither gap nor span is limited")
    if max(bounds.values(), default=0) > budget:
        raise ValueError(f"the bound of {max(bounds.values())} occurrences is above the budget of {budget}")
    way = "partitioned" if max(bounds.values(), default=0) > GROUP_LIMIT else "grouped"
    return Plan(total, patterns.threshold(min_support, total), bounds, way, notes)
