"""Baselines and ablations to compare the miner with."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relseq.functions import taxonomy
from relseq.operators import corpus as corpora
from relseq.operators import matching, patterns, refine, typemining
from relseq.operators.corpus import Corpus
from relseq.operators.typemining import Mined

LOCAL_ITEMS = 500_000  # items behind a prefix that the library may bring to one task
REPEATS = 1000  # copies of a row that stand side by side


def presence(corpus: Corpus, skeletons: list[str], max_gap: int | None = None, max_span: int | None = None) -> DataFrame:
    """(skeleton, support) by a search that stops at the first match: no occurrence is kept."""
    wanted = [patterns.parse(s) for s in skeletons]
    rows = matching.search(matching.multiset_filter(corpus, wanted), wanted, max_gap, max_span, running=True, first_only=True)
    return rows.where("lambda is not null").groupBy("skeleton").agg(F.count("*").alias("support"))


def reachable(types: list[str], txns: list[int], skeleton: patterns.Skeleton, max_gap: int | None) -> bool:
    """Presence by moving forward a set of end positions, event by event: quadratic with gaps, linear without."""
    want, breaks = skeleton
    ends = [i for i, t in enumerate(types) if t == want[0]]
    for t, brk in zip(want[1:], breaks):
        ends = [j for j in range(len(types)) if types[j] == t and any(i < j and (max_gap is None or j - i <= max_gap) and (txns[j] > txns[i]) == brk for i in ends)]
        if not ends:
            return False
    return bool(ends)


def presence_forward(corpus: Corpus, skeletons: list[str], max_gap: int | None = None) -> DataFrame:
    wanted = [(s, patterns.parse(s)) for s in skeletons]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = [name for types, txns in zip(*(c.to_pylist() for c in batch.columns)) for name, s in wanted if reachable(types, txns, s, max_gap)]
            yield pa.RecordBatch.from_arrays([pa.array(out, pa.string())], ["skeleton"])

    flat = corpus.sequences.select(F.transform("events", lambda e: e["type"]).alias("t"), F.transform("events", lambda e: e["txn"]).alias("x"))
    return flat.mapInArrow(run, "skeleton string").groupBy("skeleton").agg(F.count("*").alias("support"))


def first_occurrence(mined: Mined) -> Mined:
    """Only the first occurrence of a skeleton in each sequence is refined: support is lost."""
    from dataclasses import replace

    return replace(mined, rows=mined.rows.withColumn("found", typemining.cap_row("found", 1)), complete=False, grow=None)


def plain(corpus: Corpus, min_support: float, max_events: int | None = None) -> Mined:
    """Frequent type sequences without any tree."""
    return typemining.mine(corpora.scenario(corpus, "plain"), min_support, max_events=max_events)


def taxonomic(corpus: Corpus, min_support: float, max_gap: int | None = None, max_events: int = 2, kind: str = "maximal") -> DataFrame:
    """Taxonomic sequences without relations."""
    return refine.refine(typemining.mine(corpora.scenario(corpus, "taxonomic"), min_support, max_gap, max_events=max_events), kind)


def extended_sequences(corpus: Corpus) -> DataFrame:
    """The form in which every event stands with all its ancestors: (seq_id, sequence of itemsets)."""
    every = F.transform("events", lambda e: F.struct(e["txn"].alias("txn"), F.concat(F.array(e["type"]), F.flatten(F.transform(e["concepts"], lambda c: F.transform(taxonomy.ancestors(c), lambda a: F.concat(e["type"], F.lit(":"), a))))).alias("items")))
    sets = F.transform(F.sequence(F.lit(1), F.col("n_txn")), lambda t: F.array_distinct(F.flatten(F.transform(F.filter(every, lambda e: e["txn"] == t), lambda e: e["items"]))))
    return corpus.sequences.select("seq_id", sets.alias("sequence"))


def extended_mining(corpus: Corpus, min_support: float, max_items: int = 3) -> DataFrame:
    """Taxonomic sequences by the library's pattern growth over the extended form, in which an event counts for each
    of its ancestors: (pattern, n_items, support). Items of a transaction that lie on one path are kept, so the
    result holds every generalisation, and patterns that repeat an ancestor beside its concept are left out."""
    from pyspark.ml.fpm import PrefixSpan

    found = PrefixSpan(minSupport=min_support, maxPatternLength=max_items).findFrequentSequentialPatterns(extended_sequences(corpus))
    below = lambda a, b: (a != b) & F.startswith(b, F.concat(a, F.when(F.contains(a, F.lit(":")), F.lit("/")).otherwise(F.lit(":"))))
    twice = F.exists("sequence", lambda s: F.exists(s, lambda a: F.exists(s, lambda b: below(a, b))))
    text = F.array_join(F.transform("sequence", lambda s: F.array_join(F.array_sort(s), " ")), " ; ")
    return found.where(~twice).select(text.alias("pattern"), F.aggregate("sequence", F.lit(0), lambda n, s: n + F.size(s)).alias("n_items"), F.col("freq").alias("support"))


def repeated(rows: DataFrame) -> DataFrame:
    """Every row as often as ``n`` says, dealt in blocks."""
    blocks = rows.withColumn("block", F.explode(F.sequence(F.lit(0), F.floor((F.col("n") - 1) / REPEATS)))).repartition("sequence", "block")
    return blocks.withColumn("i", F.explode(F.sequence(F.lit(1), F.least(F.lit(REPEATS), F.col("n") - F.col("block") * REPEATS)))).drop("n", "block", "i")


def prefixspan(corpus: Corpus, min_support: float, max_events: int | None = None) -> DataFrame:
    """Pattern growth by the library's own miner over type sets; comparable where no type repeats inside a
    transaction. (skeleton, n_events, support). Prefixes with more than ``LOCAL_ITEMS`` items behind them are grown by
    counts over all rows; by the library's own limit, all that follows a common prefix would meet in one task."""
    from pyspark.ml.fpm import PrefixSpan

    kinds = F.transform("events", lambda e: F.struct(e["txn"].alias("txn"), e["type"].alias("type")))
    sets = F.transform(F.sequence(F.lit(1), F.element_at("events", -1)["txn"]), lambda t: F.array_sort(F.array_distinct(F.transform(F.filter(kinds, lambda e: e["txn"] == t), lambda e: e["type"]))))
    number = F.sum("weight") if "weight" in corpus.sequences.columns else F.count("*")
    found = PrefixSpan(minSupport=min_support, maxPatternLength=max_events or 2**31 - 1, maxLocalProjDBSize=LOCAL_ITEMS).findFrequentSequentialPatterns(repeated(corpus.sequences.groupBy(sets.alias("sequence")).agg(number.alias("n"))))
    text = F.array_join(F.transform("sequence", lambda s: F.array_join(F.array_sort(s), " ")), " ; ")
    return found.select(text.alias("skeleton"), F.aggregate("sequence", F.lit(0), lambda n, s: n + F.size(s)).alias("n_events"), F.col("freq").alias("support"))


def prefix_growth(corpus: Corpus, min_support: float, max_gap: int | None = None, max_events: int | None = None) -> dict[str, int]:
    """Supports by growing prefixes over projected rows, presence only. A row keeps, for each frequent prefix, the
    positions at which it can end: without a gap the earliest in each transaction, since no later one reaches
    further, with a gap all of them. What follows those ends is all that is looked at; extensions are read off
    the projected rows, so there are no candidates to generate, and one count an extension travels."""
    theta = patterns.threshold(min_support, corpus.size())
    ends = "array<struct<skeleton:string,ends:array<int>>>"

    def earliest(e):
        return F.filter(e, lambda p, i: (i == 0) | (F.element_at("events", p)["txn"] != F.element_at("events", F.get(e, i - 1))["txn"]))

    def step(p):
        """Every event behind an end, under the name that it would give the prefix."""

        def behind(end):
            last = F.element_at("events", end)
            window = F.slice("events", end + 1, F.greatest(F.lit(0), F.size("events") - end) if max_gap is None else F.lit(max_gap))
            return F.transform(window, lambda e: F.struct(F.concat(p["skeleton"], F.when(e["txn"] > last["txn"], patterns.BREAK).otherwise(patterns.SAME), e["type"]).alias("skeleton"), e["pos"].alias("pos")))

        return F.flatten(F.transform(p["ends"], behind))

    def gathered(steps):
        names = F.array_distinct(F.transform(steps, lambda s: s["skeleton"]))
        at = lambda n: F.array_sort(F.array_distinct(F.transform(F.filter(steps, lambda s: s["skeleton"] == n), lambda s: s["pos"])))
        return F.transform(names, lambda n: F.struct(n.alias("skeleton"), at(n).alias("ends")))

    first = F.transform("events", lambda e: F.struct(e["type"].alias("skeleton"), e["pos"].alias("pos")))
    rows = corpus.sequences.select("seq_id", "events", F.array(first).alias("steps"))
    held: list[DataFrame] = []
    out: dict[str, int] = {}
    try:
        while True:
            rows = rows.withColumn("now", F.flatten(F.transform("steps", gathered)).cast(ends))
            if max_gap is None:
                rows = rows.withColumn("now", F.transform("now", lambda p: F.struct(p["skeleton"].alias("skeleton"), earliest(p["ends"]).alias("ends"))))
            rows = rows.select("seq_id", "events", "now").persist()
            held.append(rows)
            # A prefix stands once in a row.
            counts = rows.select(F.explode("now").alias("p")).groupBy("p.skeleton").agg(F.count("*").alias("support")).where(F.col("support") >= theta)
            level = {r["skeleton"]: int(r["support"]) for r in counts.collect()}  # one row a frequent prefix
            out |= level
            if not level or (max_events is not None and len(patterns.parse(next(iter(level)))[0]) >= max_events):
                return out
            alive = F.filter("now", lambda p: F.array_contains(F.array(*[F.lit(x) for x in sorted(level)]), p["skeleton"]))
            rows = rows.where(F.size(alive) > 0).select("seq_id", "events", F.transform(alive, step).alias("steps"))
    finally:
        for df in held:
            df.unpersist()


def row_support(leafs: DataFrame) -> DataFrame:
    """(skeleton, slot, concept, row_support, support): counting rows as textbook itemset mining does, beside
    counting sequences."""
    long = refine.items(leafs)
    rows = long.groupBy("skeleton", "slot", "concept").agg(F.count("*").alias("row_support"))
    return rows.join(refine.item_support(leafs), ["skeleton", "slot", "concept"])


def fpgrowth_items(leafs: DataFrame, skeleton: str, min_rows: float) -> DataFrame:
    """The library's itemset miner on the occurrence rows of one skeleton."""
    from pyspark.ml.fpm import FPGrowth

    rows = leafs.where(F.col("skeleton") == skeleton).select(F.array_distinct(F.flatten(F.transform("leaf", lambda c, i: F.transform(taxonomy.ancestors(c), lambda a: F.concat((i + 1).cast("string"), F.lit(":"), a))))).alias("items"))
    return FPGrowth(minSupport=min_rows, minConfidence=1.0).fit(rows).freqItemsets


def pruning_steps(corpus: Corpus, skeletons: list[str], max_gap: int | None = None) -> DataFrame:
    """(variant, steps, pruned): the recursive search with and without type-count checks."""
    wanted = [patterns.parse(s) for s in skeletons]
    parts = []
    for name, rows, running in (("none", corpus.sequences, False), ("filter", matching.multiset_filter(corpus, wanted), False), ("running", matching.multiset_filter(corpus, wanted), True)):
        found = matching.search(rows, wanted, max_gap, running=running)
        parts.append(found.agg(F.sum("steps").alias("steps"), F.sum("pruned").alias("pruned")).select(F.lit(name).alias("variant"), "steps", "pruned"))
    return parts[0].unionByName(parts[1]).unionByName(parts[2])
