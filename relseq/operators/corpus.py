"""Corpora: typed events packed into one row per sequence.

Long layout: ``seq_id, txn_key, type, concepts array<string>, attrs struct, event_id``. Packed layout:
``seq_id, events array<struct<pos, txn, type, concepts, attrs, event_id>>, n_events, n_txn`` and a column
``n_<type>`` for each type. Positions count events from 1; transactions are dense from 1, and a separator
stands between events of different transactions, never as a row of its own.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from relseq.functions.relations import Relation, oriented

BREAK = " ; "
SAME = " "


@dataclass(frozen=True)
class Corpus:
    """A packed table and its schemas: trees by event type, and relations by pair of types."""

    sequences: DataFrame
    trees: dict[str, list[str]]  # event type -> tree ids of its concept array
    relations: tuple[Relation, ...] = ()
    with_concepts: bool = True

    @property
    def types(self) -> list[str]:
        return sorted(self.trees)

    def size(self) -> int:
        return int(self.sequences.agg(F.sum("weight")).first()[0] or 0) if "weight" in self.sequences.columns else self.sequences.count()


def keep_valid(events: DataFrame) -> DataFrame:
    """Rows with a sequence key and a type; a missing concept array reads as all roots later."""
    return events.where(F.col("seq_id").isNotNull() & F.col("type").isNotNull())


def dedupe(events: DataFrame) -> DataFrame:
    """Equal events of a transaction are one: the smallest event_id stays. A partial aggregate, so no
    transaction is gathered before it is small."""
    rest = [c for c in events.columns if c not in ("seq_id", "txn_key", "type", "concepts", "event_id")]
    best = F.min_by(F.struct("event_id", *rest), "event_id").alias("x")
    return events.groupBy("seq_id", "txn_key", "type", "concepts").agg(best).select("seq_id", "txn_key", "type", "concepts", "x.*")


def pack(events: DataFrame, types: list[str]) -> DataFrame:
    """One row per sequence with canonical order: transaction, type, concepts in pre-order, event_id."""
    # Structs sort field by field, so the order of the fields is the canonical order.
    item = F.struct("txn_key", "type", "concepts", "event_id", "attrs")
    rows = events.withColumn("concepts", F.coalesce("concepts", F.array().cast("array<string>"))).groupBy("seq_id").agg(F.array_sort(F.collect_list(item)).alias("xs"))
    rows = rows.withColumn("ks", F.array_distinct(F.transform("xs", lambda x: x["txn_key"])))
    events_col = F.transform("xs", lambda x, i: F.struct((i + 1).cast("int").alias("pos"), F.array_position("ks", x["txn_key"]).cast("int").alias("txn"), x["type"].alias("type"), x["concepts"].alias("concepts"), x["attrs"].alias("attrs"), x["event_id"].alias("event_id")))
    rows = rows.select("seq_id", events_col.alias("events"), F.size("xs").alias("n_events"), F.size("ks").alias("n_txn"))
    return rows.select("*", *[_count(t).alias(f"n_{t}") for t in types])


def _count(kind: str) -> Column:
    """Events of one type; a lambda of two parameters would be given the index."""
    return F.size(F.filter("events", lambda e: e["type"] == kind))


def build(events: DataFrame, trees: dict[str, list[str]], relations: list[Relation] = (), distinct: bool = True) -> Corpus:
    events = keep_valid(events)
    return Corpus(pack(dedupe(events) if distinct else events, sorted(trees)), trees, tuple(relations))


def build_plain(events: DataFrame, trees: dict[str, list[str]]) -> Corpus:
    """``condensed`` of the plain scenario of ``build``, from the long layout without attributes and ids: rows travel
    once by sequence, and then what is distinct in types and transactions. Concepts only tell equal events apart, so
    any array will do that is equal where they are."""
    rows = keep_valid(events).select("seq_id", "txn_key", "type", "concepts").repartition("seq_id").distinct()
    blocks = rows.groupBy("seq_id", "txn_key", "type").agg(F.count("*").cast("int").alias("n"))
    rows = blocks.groupBy("seq_id").agg(F.array_sort(F.collect_list(F.struct("txn_key", "type", "n"))).alias("xs"))
    rows = rows.withColumn("ks", F.array_distinct(F.transform("xs", lambda x: x["txn_key"])))
    each = F.flatten(F.transform("xs", lambda x: F.array_repeat(F.struct(F.array_position("ks", x["txn_key"]).cast("int").alias("txn"), x["type"].alias("type")), x["n"])))
    rows = rows.select(each.alias("each")).select(F.array_join(F.transform("each", lambda e: e["type"]), SAME).alias("types"), F.transform("each", lambda e: e["txn"]).alias("txns"))
    rows = rows.groupBy("types", "txns").agg(F.count("*").alias("weight"))
    none = F.array().cast("array<string>")
    seen = F.zip_with(F.split("types", SAME), "txns", lambda t, x: F.struct(x.alias("txn"), t.alias("type")))
    events_col = F.transform(seen, lambda e, i: F.struct((i + 1).cast("int").alias("pos"), e["txn"].alias("txn"), e["type"].alias("type"), none.alias("concepts")))
    rows = rows.select(F.array().cast("array<array<string>>").alias("related"), events_col.alias("events"), "weight")
    return Corpus(rows.withColumn("seq_id", F.monotonically_increasing_id().cast("string")), trees, (), False)


def scenario(corpus: Corpus, kind: str) -> Corpus:
    """``full``; ``relations`` leaves out event trees; ``taxonomic`` leaves out relations; ``plain`` both."""
    keep_relations, keep_concepts = {"full": (True, True), "relations": (True, False), "taxonomic": (False, True), "plain": (False, False)}[kind]
    return replace(corpus, relations=corpus.relations if keep_relations else (), with_concepts=keep_concepts)


def condensed(corpus: Corpus, days: bool = False) -> Corpus:
    """Sequences that agree in all that the scenario sees (types, transactions, concepts, relations of all pairs) as one
    row with their number, ``weight``. Attributes are left out but the day, if asked for; ``related`` holds the
    relations of each pair of events, by the later event, then the earlier one."""
    if "weight" in corpus.sequences.columns:
        return corpus
    relate = oriented(list(corpus.relations))
    parts = [lambda e: e["pos"].alias("pos"), lambda e: e["txn"].alias("txn"), lambda e: e["type"].alias("type"), lambda e: (e["concepts"] if corpus.with_concepts else F.array().cast("array<string>")).alias("concepts")]
    if days:
        parts.append(lambda e: F.struct(e["attrs"]["day"].alias("day")).alias("attrs"))
    events = F.transform("events", lambda e: F.struct(*[p(e) for p in parts]))
    pairs = F.flatten(F.transform("events", lambda b: F.transform(F.slice("events", 1, b["pos"] - 1), lambda a: relate(a, b))))
    related = pairs if corpus.relations else F.array().cast("array<array<string>>")
    rows = corpus.sequences.select(related.alias("related"), events.alias("seen")).groupBy(F.col("seen").alias("events"), "related").agg(F.count("*").alias("weight"))
    return replace(corpus, sequences=rows.withColumn("seq_id", F.monotonically_increasing_id().cast("string")))


def looked_up(a: Column, b: Column) -> Column:
    """The relations of an earlier and a later event of a ``condensed`` row."""
    return F.get(F.col("related"), F.shiftright((b["pos"] - 1) * (b["pos"] - 2), 1) + a["pos"] - 1)


def sample(corpus: Corpus, tenths: int, key: Column) -> Corpus:
    """The sequences whose ``key`` modulo 10 is below ``tenths``."""
    return replace(corpus, sequences=corpus.sequences.where(F.pmod(key, F.lit(10)) < tenths))


def drop_long(corpus: Corpus, max_events: int) -> Corpus:
    return replace(corpus, sequences=corpus.sequences.where(F.col("n_events") <= max_events))


def drop_crowded(corpus: Corpus, most: int) -> Corpus:
    """Leaves out sequences with more than ``most`` events of one type."""
    fine = F.lit(True)
    for t in corpus.types:
        fine = fine & (F.col(f"n_{t}") <= most)
    return replace(corpus, sequences=corpus.sequences.where(fine))


def unpack(corpus: Corpus) -> DataFrame:
    """The long canonical layout."""
    return corpus.sequences.select("seq_id", F.explode("events").alias("e")).select("seq_id", "e.*")


# -- views --------------------------------------------------------------------------------------------------


def n_elements() -> Column:
    """Length with separators."""
    return F.col("n_events") + F.col("n_txn") - 1


def element_index(pos: Column, txn: Column) -> Column:
    """Place of an event when separators are counted too."""
    return pos + txn - 1


def type_view(events: Column) -> Column:
    """``A A ; F``"""
    joined = F.transform(events, lambda e, i: F.concat(F.when(i == 0, "").when(F.element_at(events, F.greatest(i, F.lit(1)))["txn"] == e["txn"], SAME).otherwise(BREAK), e["type"]))
    return F.array_join(joined, "")


def project(events: Column, places: Column) -> Column:
    """The events at the given positions."""
    return F.transform(places, lambda p: F.element_at(events, p))


def concept_view(events: Column, places: Column, relate, with_concepts: bool = True) -> Column:
    """The leaf row of an occurrence: for each event its concepts, then its relations to the earlier ones."""

    def own(i: Column) -> Column:
        e = F.element_at(events, F.element_at(places, i))
        earlier = F.when(i > 1, F.flatten(F.transform(F.sequence(F.lit(1), F.greatest(i - 1, F.lit(1))), lambda j: relate(F.element_at(events, F.element_at(places, j)), e)))).otherwise(F.array().cast("array<string>"))
        return F.concat(e["concepts"], earlier) if with_concepts else earlier

    return F.flatten(F.transform(F.sequence(F.lit(1), F.size(places)), own))


def full_view(events: Column, relate) -> Column:
    """Every event with its concepts and its relations to all earlier events; quadratic, for small sequences."""
    return F.transform(events, lambda e, i: F.struct(e["type"].alias("type"), e["concepts"].alias("concepts"), F.transform(F.slice(events, 1, i), lambda p: relate(p, e)).alias("relations")))


def slot_names(types: list[str], trees: dict[str, list[str]], relations: tuple[Relation, ...], with_concepts: bool = True) -> list[str]:
    """The slots of a skeleton in leaf-row order."""
    out: list[str] = []
    for i, t in enumerate(types, 1):
        out += [f"{i}.{x}" for x in trees[t]] if with_concepts else []
        for j, s in enumerate(types[: i - 1], 1):
            pair = tuple(sorted((s, t)))
            out += [f"{j}-{i}.{n}" for n, r in enumerate((r for r in relations if (r.type_a, r.type_b) == pair), 1)]
    return out


def capped_occurrences(df: DataFrame, most: int, by: list[str]) -> DataFrame:
    """At most ``most`` rows for each of ``by``; the result is marked incomplete by its caller."""
    return df.withColumn("__n", F.row_number().over(Window.partitionBy(*by).orderBy("lambda"))).where(F.col("__n") <= most).drop("__n")


def length_cut(corpus: Corpus, share: float) -> int:
    """The number of events that this share of sequences does not exceed (approximate above 10,000 lengths)."""
    found = corpus.sequences.agg(F.percentile_approx("n_events", share, 10_000)).first()[0]
    return int(found or 0)


def drop_outliers(corpus: Corpus, share: float) -> Corpus:
    """Without the sequences longer than ``length_cut``: the few that would make most of the occurrences."""
    return drop_long(corpus, length_cut(corpus, share))


def length_bands(corpus: Corpus, width: int) -> DataFrame:
    """(band, from_events, sequences): a histogram of lengths in bands of equal width."""
    band = F.floor((F.col("n_events") - 1) / width).cast("int")
    return corpus.sequences.groupBy(band.alias("band")).agg(F.count("*").alias("sequences")).select("band", (F.col("band") * width + 1).alias("from_events"), "sequences")


def event_gaps(corpus: Corpus) -> DataFrame:
    """(seq_id, pos, day_gap): days since the event before, null for the first."""
    rows = unpack(corpus).select("seq_id", "pos", F.col("attrs.day").alias("day"))
    return rows.select("seq_id", "pos", (F.col("day") - F.lag("day").over(Window.partitionBy("seq_id").orderBy("pos"))).alias("day_gap"))
