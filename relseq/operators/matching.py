"""Occurrences of skeletons, by three equivalent strategies.

``grow`` extends all occurrences of length k by one event inside each sequence's own row: every occurrence of
length k+1 has exactly one prefix, and only the last step's gap and the whole span are new. ``kernel`` is a
recursive search per sequence with running type counts, in Arrow batches. ``sql`` joins events on the
sequence with bands on positions.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from relseq.operators import patterns
from relseq.operators.corpus import BREAK, SAME, Corpus, unpack
from relseq.operators.patterns import Skeleton

OCCURRENCE = "array<struct<skeleton:string,lambda:array<int>>>"
UNITS = ("event", "element", "transaction", "time")


def measure(event: Column, unit: str) -> Column:
    """What gaps and spans count: events, elements with separators, transactions, or the ``day`` attribute."""
    if unit == "event":
        return event["pos"]
    if unit == "element":
        return event["pos"] + event["txn"] - 1
    if unit == "transaction":
        return event["txn"]
    if unit == "time":
        return event["attrs"]["day"]
    raise ValueError(f"unit must be one of {UNITS}")


def first_level(events: Column) -> Column:
    return F.transform(events, lambda e: F.struct(e["type"].alias("skeleton"), F.array(e["pos"]).alias("lambda"))).cast(OCCURRENCE)


def grown(events: Column, occurrences: Column, allowed: list[str], max_gap: int | None, max_span: int | None, unit: str = "event") -> Column:
    """One-step extensions whose skeleton is among ``allowed`` (a bounded, driver-made list)."""
    wanted = F.array(*[F.lit(s) for s in allowed]) if allowed else F.array().cast("array<string>")

    def steps(o: Column) -> Column:
        last = F.element_at(events, F.element_at(o["lambda"], -1))
        first = F.element_at(events, F.element_at(o["lambda"], 1))
        begin = last["pos"] + 1
        window = F.slice(events, begin, F.lit(max_gap)) if max_gap is not None and unit == "event" else F.slice(events, begin, F.greatest(F.size(events) - begin + 1, F.lit(0)))

        def fits(e: Column) -> Column:
            ok = F.lit(True)
            if max_gap is not None and unit != "event":
                ok = ok & (measure(e, unit) - measure(last, unit) <= max_gap)
            if max_span is not None:
                ok = ok & (measure(e, unit) - measure(first, unit) <= max_span)
            return ok

        def add(e: Column) -> Column:
            name = F.concat(o["skeleton"], F.when(e["txn"] > last["txn"], BREAK).otherwise(SAME), e["type"])
            return F.struct(name.alias("skeleton"), F.array_append(o["lambda"], e["pos"]).alias("lambda"))

        near = F.filter(window, fits) if max_span is not None or (max_gap is not None and unit != "event") else window
        return F.transform(near, add)

    return F.filter(F.flatten(F.transform(occurrences, steps)), lambda o: F.array_contains(wanted, o["skeleton"])).cast(OCCURRENCE)


def multiset_filter(corpus: Corpus, skeletons: list[Skeleton]) -> DataFrame:
    """Sequences whose type counts admit at least one of the skeletons: flat columns, so it reaches the scan."""
    ok = F.lit(False)
    for s in skeletons:
        one = F.lit(True)
        for t, n in patterns.need(s).items():
            one = one & (F.col(f"n_{t}") >= n)
        ok = ok | one
    return corpus.sequences.where(ok)


def occurrences(corpus: Corpus, skeletons: list[str], max_gap: int | None = None, max_span: int | None = None, unit: str = "event", strategy: str = "grow", prune: bool = True) -> DataFrame:
    """(seq_id, skeleton, lambda) of all occurrences of the given skeletons."""
    wanted = [patterns.parse(s) for s in skeletons]
    if strategy == "sql":
        parts = [_joined(corpus, s, max_gap, max_span, unit) for s in wanted]
        out = parts[0]
        for p in parts[1:]:
            out = out.unionByName(p)
        return out
    rows = multiset_filter(corpus, wanted) if prune else corpus.sequences
    if strategy == "kernel":
        return search(rows, wanted, max_gap, max_span, unit, prune).where("lambda is not null").select("seq_id", "skeleton", "lambda")
    prefixes: dict[int, set[str]] = {}
    for types, breaks in wanted:
        for k in range(1, len(types) + 1):
            prefixes.setdefault(k, set()).add(patterns.render((types[:k], breaks[: k - 1])))
    now = F.filter(first_level(F.col("events")), lambda o: F.array_contains(F.array(*[F.lit(s) for s in sorted(prefixes[1])]), o["skeleton"]))
    out = rows.select("seq_id", "events", now.alias("now"), F.array().cast(OCCURRENCE).alias("found"))
    for k in range(1, max(prefixes) + 1):
        done = F.filter("now", lambda o: F.array_contains(F.array(*[F.lit(s) for s in skeletons]), o["skeleton"]))
        out = out.withColumn("found", F.concat("found", done))
        if k + 1 in prefixes:
            out = out.withColumn("now", grown(F.col("events"), F.col("now"), sorted(prefixes[k + 1]), max_gap, max_span, unit))
    return out.select("seq_id", F.explode("found").alias("o")).select("seq_id", "o.skeleton", "o.lambda")


def _joined(corpus: Corpus, s: Skeleton, max_gap, max_span, unit: str) -> DataFrame:
    """Self-joins on the sequence with bands on positions."""
    types, breaks = s
    base = unpack(corpus)
    base = base.select("seq_id", "pos", "txn", "type", measure(F.struct(*base.columns), unit).alias("at"))
    out = base.where(F.col("type") == types[0]).select("seq_id", F.array("pos").alias("lambda"), F.col("pos").alias("p"), F.col("txn").alias("t"), F.col("at").alias("a"), F.col("at").alias("a0"))
    for t, brk in zip(types[1:], breaks):
        step = base.where(F.col("type") == t).select(F.col("seq_id").alias("s2"), F.col("pos").alias("p2"), F.col("txn").alias("t2"), F.col("at").alias("a2"))
        on = (F.col("seq_id") == F.col("s2")) & (F.col("p2") > F.col("p")) & ((F.col("t2") > F.col("t")) if brk else (F.col("t2") == F.col("t")))
        if max_gap is not None:
            on = on & (F.col("a2") - F.col("a") <= max_gap)
        if max_span is not None:
            on = on & (F.col("a2") - F.col("a0") <= max_span)
        out = out.join(step, on).select("seq_id", F.array_append("lambda", F.col("p2")).alias("lambda"), F.col("p2").alias("p"), F.col("t2").alias("t"), F.col("a2").alias("a"), "a0")
    return out.select("seq_id", F.lit(patterns.render(s)).alias("skeleton"), "lambda")


def search_one(types: list[str], txns: list[int], at: list[int], s: Skeleton, max_gap: int | None, max_span: int | None, running: bool, first_only: bool = False) -> tuple[list[list[int]], int, int]:
    """Index vectors of one skeleton in one sequence, steps taken, and branches given up by type counts."""
    want, breaks = s
    n, k = len(types), len(want)
    tail: list[dict[str, int]] = [{}]
    for t in reversed(types):
        tail.append(tail[-1] | {t: tail[-1].get(t, 0) + 1})
    tail.reverse()
    needs: list[dict[str, int]] = [{}]
    for t in reversed(want):
        needs.append(needs[-1] | {t: needs[-1].get(t, 0) + 1})
    needs.reverse()
    found: list[list[int]] = []
    steps = pruned = 0
    stack: list[tuple[int, list[int]]] = [(0, [])]
    while stack:
        i, chosen = stack.pop()
        m = len(chosen)
        if m == k:
            found.append([c + 1 for c in chosen])
            if first_only:
                break
            continue
        if i >= n:
            continue
        steps += 1
        if running and any(tail[i].get(t, 0) < c for t, c in needs[m].items()):
            pruned += 1
            continue
        if m:
            last = chosen[-1]
            if (max_gap is not None and at[i] - at[last] > max_gap) or (max_span is not None and at[i] - at[chosen[0]] > max_span) or (not breaks[m - 1] and txns[i] > txns[last]):
                continue
        stack.append((i + 1, chosen))
        if types[i] == want[m] and (not m or (txns[i] > txns[chosen[-1]]) == breaks[m - 1]):
            stack.append((i + 1, [*chosen, i]))
    return sorted(found), steps, pruned


def search(rows: DataFrame, wanted: list[Skeleton], max_gap=None, max_span=None, unit: str = "event", running: bool = True, first_only: bool = False) -> DataFrame:
    """(seq_id, skeleton, lambda, steps, pruned): the recursive search; one row with a null lambda reports the
    steps of a search without result."""
    names = [patterns.render(s) for s in wanted]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[tuple] = []
            for seq, types, txns, at in zip(*(c.to_pylist() for c in batch.columns)):
                for name, s in zip(names, wanted):
                    found, steps, pruned = search_one(types, txns, at, s, max_gap, max_span, running, first_only)
                    for n, lam in enumerate(found or [None]):
                        out.append((seq, name, lam, steps if n == 0 else 0, pruned if n == 0 else 0))
            cols = list(zip(*out)) or [[]] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.string(), pa.string(), pa.list_(pa.int32()), pa.int64(), pa.int64()))], ["seq_id", "skeleton", "lambda", "steps", "pruned"])

    flat = rows.select(F.col("seq_id").cast("string"), F.transform("events", lambda e: e["type"]).alias("types"), F.transform("events", lambda e: e["txn"]).alias("txns"), F.transform("events", lambda e: measure(e, unit).cast("int")).alias("at"))
    out = flat.mapInArrow(run, "seq_id string, skeleton string, `lambda` array<int>, steps long, pruned long")
    return out




def permuted(events: Column, places: Column, k: int) -> Column:
    """An occurrence and all its variants that swap events of one type in one transaction: with these the matching
    definition is met without demanding increasing positions. ``k`` bounds the events of a skeleton."""

    def swap(lam: Column, i: int) -> Column:
        a, b = F.element_at(events, F.get(lam, F.lit(i))), F.element_at(events, F.get(lam, F.lit(i + 1)))
        fits = (F.size(lam) > i + 1) & (a["type"] == b["type"]) & (a["txn"] == b["txn"])
        turned = F.concat(F.slice(lam, 1, i), F.array(F.get(lam, F.lit(i + 1)), F.get(lam, F.lit(i))), F.slice(lam, i + 3, k))
        return F.when(fits, turned).otherwise(lam)

    out = F.array(places)
    for _ in range(k * (k - 1) // 2):  # as many neighbour swaps reach every order
        for i in range(k - 1):
            out = _with_swaps(out, swap, i)
    return out


def _with_swaps(found: Column, swap, i: int) -> Column:
    return F.array_distinct(F.concat(found, F.transform(found, lambda lam: swap(lam, i))))
