"""Stage 1: frequent skeletons, level by level, and all their occurrences.

Skeletons see only types and transactions, so sequences that agree in these are counted once, with their number. A
level is counted by moving forward, for each end position, the number of occurrences that end there: no occurrence is
made or stored to count it, and only counts per candidate travel. Candidates are built on the driver from the frequent
skeletons of the level before; their number depends on types and length, not on the data. The occurrences themselves
are grown inside each sequence's own row when they are asked for.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass
from itertools import count

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relseq.operators import matching, patterns
from relseq.operators.corpus import Corpus
from relseq.operators.matching import OCCURRENCE
from relseq.session import ship

Level = tuple[frozenset[str], bool]  # the frequent skeletons of a level, and whether their occurrences are capped


@dataclass
class Mined:
    """Frequent skeletons, and per sequence the occurrences of those (column ``found``)."""

    corpus: Corpus
    total: int
    threshold: int
    skeletons: dict[str, tuple[int, int]]  # skeleton -> (support, occurrences)
    rows: DataFrame  # seq_id, events, found
    complete: bool = True
    grow: Callable[[DataFrame], DataFrame] | None = None  # adds ``found`` to any table with ``events``
    timed: bool = False  # growing reads the ``day`` attribute
    stored: int = 0  # occurrences of the largest skeleton in the corpus' rows, whatever number these stand for
    limits: tuple[int | None, int | None, str] | None = None  # gap, span and their unit, if no occurrence was capped

    def table(self) -> DataFrame:
        """(skeleton, n_events, support, occurrences)."""
        data = [(s, len(patterns.parse(s)[0]), a, b) for s, (a, b) in sorted(self.skeletons.items())]
        return self.rows.sparkSession.createDataFrame(data, "skeleton string, n_events int, support long, occurrences long")

    def occurrences(self) -> DataFrame:
        return self.rows.select("seq_id", F.explode("found").alias("o")).select("seq_id", "o.skeleton", "o.lambda")


def cap_row(column: str, per_sequence: int):
    """At most ``per_sequence`` occurrences of each skeleton, the first ones."""
    return F.filter(column, lambda o, i: F.size(F.filter(F.slice(F.col(column), 1, i), lambda p: p["skeleton"] == o["skeleton"])) < per_sequence).cast(OCCURRENCE)


def views(corpus: Corpus, unit: str = "event") -> DataFrame:
    """(types, txns, at, n, own): what skeletons, gaps and spans see of a sequence, how many sequences look so, and in
    how many rows of the corpus."""
    if unit not in matching.UNITS:
        raise ValueError(f"unit must be one of {matching.UNITS}")
    at = F.transform("events", lambda e: matching.measure(e, unit).cast("long"))
    number = F.sum("weight") if "weight" in corpus.sequences.columns else F.count("*")
    seen = corpus.sequences.select("*", F.transform("events", lambda e: e["type"]).alias("types"), F.transform("events", lambda e: e["txn"]).alias("txns"), at.alias("at"))
    return seen.groupBy("types", "txns", "at").agg(number.alias("n"), F.count("*").alias("own"))


def near(a, b, most: int | None) -> bool:
    return most is None or (a is not None and b is not None and b - a <= most)


def tally(types: list[str], txns: list[int], at: list, levels: list[frozenset[str]], max_gap: int | None, max_span: int | None, by_place: bool) -> dict[str, int]:
    """Occurrences of each skeleton of the last of ``levels`` in one sequence, the skeletons of the others being their
    prefixes. An end position holds (skeleton, first position) with the number of occurrences; first positions are
    kept apart only under a span. ``by_place``: gaps count events."""
    n = len(types)
    spans = max_span is not None
    now = [{(t, i if spans else 0): 1} if t in levels[0] else {} for i, t in enumerate(types)]
    for names in levels[1:]:
        longer: list[dict] = [{} for _ in range(n)]
        for i, own in enumerate(now):
            if not own:
                continue
            for j in range(i + 1, min(n, i + 1 + max_gap) if by_place and max_gap is not None else n):
                if not by_place and not near(at[i], at[j], max_gap):
                    continue
                tail = (patterns.BREAK if txns[j] > txns[i] else patterns.SAME) + types[j]
                to = longer[j]
                for (name, first), c in own.items():
                    name += tail
                    if name in names and (not spans or near(at[first], at[j], max_span)):
                        to[name, first] = to.get((name, first), 0) + c
        now = longer
    out: dict[str, int] = {}
    for own in now:
        for (name, _), c in own.items():
            out[name] = out.get(name, 0) + c
    return out


def tally_capped(types: list[str], txns: list[int], at: list, levels: list[Level], max_gap: int | None, max_span: int | None, by_place: bool, most: int) -> dict[str, int]:
    """The same where a capped level keeps the first ``most`` occurrences of each skeleton: these are told one by one."""
    n = len(types)
    now: list[tuple[str, int, int]] = [(t, i, i) for i, t in enumerate(types)]  # skeleton, first and last position
    counts: dict[str, int] = {}
    for k, (names, capped) in enumerate(levels):
        if k:
            grown = []
            for name, first, i in now:
                for j in range(i + 1, min(n, i + 1 + max_gap) if by_place and max_gap is not None else n):
                    if (by_place or near(at[i], at[j], max_gap)) and near(at[first], at[j], max_span):
                        grown.append((name + (patterns.BREAK if txns[j] > txns[i] else patterns.SAME) + types[j], first, j))
            now = grown
        counts = {}
        kept = []
        for o in now:
            if o[0] in names:
                counts[o[0]] = counts.get(o[0], 0) + 1
                if not capped or counts[o[0]] <= most:
                    kept.append(o)
        now = kept
    return counts


def counted(seen: DataFrame, levels: list[Level], max_gap: int | None, max_span: int | None, unit: str, per_sequence: int | None) -> DataFrame:
    """(skeleton, support, occurrences, stored) of the last level's candidates over ``views``."""
    by_place = unit == "event"
    plain = [names for names, _ in levels]
    capped = any(c for _, c in levels)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        support: dict[str, int] = {}
        occurrences: dict[str, int] = {}
        stored: dict[str, int] = {}
        for batch in batches:
            for types, txns, at, n, own in zip(*(c.to_pylist() for c in batch.columns)):
                found = tally_capped(types, txns, at, levels, max_gap, max_span, by_place, per_sequence) if capped else tally(types, txns, at, plain, max_gap, max_span, by_place)
                for name, c in found.items():
                    support[name] = support.get(name, 0) + n
                    occurrences[name] = occurrences.get(name, 0) + n * c
                    stored[name] = stored.get(name, 0) + own * c
        numbers = [pa.array(list(x.values()), pa.int64()) for x in (support, occurrences, stored)]
        yield pa.RecordBatch.from_arrays([pa.array(list(support), pa.string()), *numbers], ["skeleton", "support", "occurrences", "stored"])

    parts = seen.select("types", "txns", "at", "n", "own").mapInArrow(run, "skeleton string, support long, occurrences long, stored long")
    return parts.groupBy("skeleton").agg(*[F.sum(x).alias(x) for x in ("support", "occurrences", "stored")])


def with_found(rows: DataFrame, levels: list[Level], max_gap: int | None, max_span: int | None, unit: str, per_sequence: int | None) -> DataFrame:
    """Adds ``found``, the occurrences of the levels' skeletons, to rows with ``events``."""
    rows = rows.withColumns({"now": F.array().cast(OCCURRENCE), "found": F.array().cast(OCCURRENCE)})
    for k, (names, capped) in enumerate(levels):
        if not names:
            break
        wanted = sorted(names)
        if k:
            now = matching.grown(F.col("events"), F.col("now"), wanted, max_gap, max_span, unit)
        else:
            now = F.filter(matching.first_level(F.col("events")), lambda o: F.array_contains(F.array(*[F.lit(s) for s in wanted]), o["skeleton"]))
        rows = rows.withColumn("now", now)
        if capped:
            rows = rows.withColumn("now", cap_row("now", per_sequence))
        rows = rows.withColumn("found", F.concat("found", "now"))
    return rows.drop("now")


def mine(
    corpus: Corpus, min_support: float, max_gap: int | None = None, max_span: int | None = None, max_events: int | None = None, unit: str = "event", strict: bool = False,
    drop_runs: int | None = None, cap: tuple[int, int] | None = None, accepts=None,
) -> Mined:
    """Frequent skeletons with all their occurrences. The search ends by itself at the first level where nothing is
    frequent; ``max_events`` ends it earlier, and the result is marked incomplete unless no candidate was left.

    ``cap=(per_sequence, when_total_over)`` keeps the first occurrences of a skeleton in a sequence once there
    are more than ``when_total_over`` in all; the result is then marked incomplete. ``accepts`` is a mining
    constraint; it is refused if it is not safe.
    """
    ship(corpus.sequences.sparkSession)
    seen = views(corpus, unit).persist()
    gapped = max_gap is not None
    found, level, complete, stored = {}, {}, True, 0
    levels: list[Level] = []
    per_sequence = cap[0] if cap else None
    try:
        first = seen.agg(F.sum("n"), F.array_distinct(F.flatten(F.collect_set(F.array_distinct("types"))))).first()  # sets of types
        total = int(first[0] or 0)
        theta = patterns.threshold(min_support, total, strict)
        allowed = frozenset(first[1] or ())
        for k in count(1):
            if k > 1:
                candidates = patterns.extend({patterns.parse(s) for s in level}, gapped, drop_runs)
                if accepts is not None:
                    patterns.check_constraint(accepts, candidates, gapped)
                    candidates = [c for c in candidates if accepts(c)]
                if not candidates:
                    break
                if max_events is not None and k > max_events:
                    complete = False
                    break
                allowed = frozenset(patterns.render(c) for c in candidates)
            told = counted(seen, [*levels, (allowed, False)], max_gap, max_span, unit, per_sequence).collect()  # one row a candidate
            counts = {r["skeleton"]: (int(r["support"]), int(r["occurrences"])) for r in told}
            stored = max([stored, *(int(r["stored"]) for r in told if r["support"] >= theta)])
            level = {s: c for s, c in counts.items() if c[0] >= theta}
            found |= level
            if not level:
                break
            capped = bool(cap and sum(c[1] for c in level.values()) > cap[1])
            complete = complete and not capped
            levels.append((frozenset(level), capped))
    finally:
        seen.unpersist()
    grow = lambda rows: with_found(rows, levels, max_gap, max_span, unit, per_sequence)
    return Mined(corpus, total, theta, found, grow(corpus.sequences.select("seq_id", "events", *[c for c in ("related", "weight") if c in corpus.sequences.columns])), complete, grow, unit == "time", stored, None if any(c for _, c in levels) else (max_gap, max_span, unit))


def parent_lists(mined: Mined, k: int) -> DataFrame:
    """(candidate, sequences): sequences in which every safe (k-1)-parent of a k-candidate occurs; the candidate
    has to be looked for nowhere else."""
    parents = {patterns.parse(s) for s in mined.skeletons if len(patterns.parse(s)[0]) == k - 1}
    candidates = patterns.extend(parents, True)
    names = F.array_distinct(F.transform("found", lambda o: o["skeleton"]))
    rows = mined.rows.select("seq_id", names.alias("names"))
    checks = [F.when(F.forall(F.array(*[F.lit(patterns.render(p)) for p in patterns.safe_subpatterns(c, True)]), lambda s: F.array_contains("names", s)), patterns.render(c)) for c in candidates]
    if not checks:
        return rows.sparkSession.createDataFrame([], "candidate string, sequences long")
    hit = rows.select(F.explode(F.array_compact(F.array(*checks))).alias("candidate"))
    return hit.groupBy("candidate").agg(F.count("*").alias("sequences"))


def interior_violations(mined: Mined, max_gap: int, theta: int | None = None) -> DataFrame:
    """Frequent skeletons with a less frequent sub-pattern that lacks an inner event: why gaps allow trimmed
    parents only. (skeleton, support, sub_pattern, sub_support)."""
    theta = theta or mined.threshold
    found = []
    for s, (support, _) in mined.skeletons.items():
        p = patterns.parse(s)
        for i in range(1, len(p[0]) - 1):
            sub = patterns.render(patterns.drop(p, i))
            have = mined.skeletons.get(sub, (0, 0))[0]
            if have < theta <= support:
                found.append((s, support, sub))
    found = sorted(set(found))
    spark = mined.rows.sparkSession
    if not found:
        return spark.createDataFrame([], "skeleton string, support long, sub_pattern string, sub_support long")
    subs = sorted({x[2] for x in found})
    counts = matching.occurrences(mined.corpus, subs, max_gap).groupBy(F.col("skeleton").alias("sub_pattern")).agg(F.count_distinct("seq_id").alias("sub_support"))
    base = spark.createDataFrame(found, "skeleton string, support long, sub_pattern string")
    return base.join(F.broadcast(counts), "sub_pattern", "left").select("skeleton", "support", "sub_pattern", F.coalesce("sub_support", F.lit(0).cast("long")).alias("sub_support"))

