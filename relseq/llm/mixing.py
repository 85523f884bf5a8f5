"""Mixing sources to target weights by capped water-filling (JVM only).

Sources get shares of the whole in proportion to their weights; no source may be repeated more than
``max_epochs`` times, and what a full source cannot take is shared among the others by weight until no
source is above its cap. The level is found in closed form from one sorted pass over the *source* table.
A source's share is then taken as whole repetitions of all its documents plus a seeded fraction: documents
stand in the order of a keyed digest, and those before the cut are taken once more.

Documents meet their source's row of the plan by a broadcast of that table, whose rows are counted first; above
``BROADCAST_SOURCES`` they are joined by source and a salt, so that no source is one task.

Defined results: null text has size 0; a very long text is one size; null source is a source of its own, ordered
last; an empty table gives an empty result; repeated rows and ties in the digest are ordered by id and size; an id
that stands in several sources is a document of each; input columns with any other names are ignored by
``plan_mix`` and kept by ``apply_mix``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from relseq.llm import store

WEIGHTS = (5, 2, 1)
MAX_EPOCHS = 3
SEED = "mix-7"
BROADCAST_SOURCES = 100_000
SALTS = 64
WORD = r"[^\x20\x09-\x0D]+"


def word_count(text):
    return F.coalesce(F.regexp_count(text, F.lit(WORD)).cast("long"), F.lit(0).cast("long"))


def source_targets(sizes: DataFrame, weights=WEIGHTS, max_epochs: int = MAX_EPOCHS) -> DataFrame:
    """``sizes(source, source_size)``, one row a source -> the same with weight and target.

    The windows run over one row for each source, never over documents.
    """
    order = Window.orderBy(F.col("source").isNull(), F.col("source"))
    cycle = F.array(*[F.lit(float(w)) for w in weights])
    rows = sizes.select("source", "source_size", F.element_at(cycle, ((F.row_number().over(order) - 1) % len(weights) + 1).cast("int")).alias("weight"))
    rows = rows.withColumn("cap", max_epochs * F.col("source_size").cast("double"))
    # Sources fill up in the order of cap / weight; before each, the level that shares what is left.
    fill = Window.orderBy((F.col("cap") / F.col("weight")), F.col("source").isNull(), F.col("source"))
    before = fill.rowsBetween(Window.unboundedPreceding, -1)
    everything = Window.partitionBy()
    rows = (
        rows.withColumn("used_cap", F.coalesce(F.sum("cap").over(before), F.lit(0.0)))
        .withColumn("used_weight", F.coalesce(F.sum("weight").over(before), F.lit(0.0)))
        .withColumn("total", F.sum("source_size").over(everything).cast("double"))
        .withColumn("all_weight", F.sum("weight").over(everything))
        .withColumn("level", (F.col("total") - F.col("used_cap")) / (F.col("all_weight") - F.col("used_weight")))
        .withColumn("open_level", F.when(F.col("level") * F.col("weight") <= F.col("cap"), F.col("level")))
        .withColumn("open_level", F.first("open_level", ignorenulls=True).over(fill.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)))
    )
    return rows.select("source", "source_size", "weight", F.least(F.col("cap"), F.col("weight") * F.col("open_level")).alias("target"))


def _keyed(docs: DataFrame, payload, id_col: str, source_col: str, text_col: str, seed: str) -> DataFrame:
    """(row, doc_id, source, size, digest, bucket): ``payload`` as a row, and what the plan goes by."""
    digest = F.md5(F.concat(F.lit(seed + ":"), F.coalesce(F.col(f"`{id_col}`").cast("string"), F.lit("null"))))
    rows = docs.select(payload.alias("row"), F.col(f"`{id_col}`").alias("doc_id"), F.col(f"`{source_col}`").alias("source"), word_count(F.col(f"`{text_col}`")).alias("size"), digest.alias("digest"))
    return rows.withColumn("bucket", F.substring("digest", 1, 3))


def plan_mix(docs: DataFrame, id_col: str = "doc_id", source_col: str = "source", text_col: str = "text", weights=WEIGHTS, max_epochs: int = MAX_EPOCHS, seed: str = SEED, partial: bool = True) -> DataFrame:
    """One row per document: id, size, source_size, target, taken, repeats.

    ``partial``: the document on which a source's cut falls gives just the words still due (``taken``), so
    a source's sum equals its rounded target; otherwise it is taken whole or not, whichever is nearer.
    """
    # Texts are read once: what is kept of a document is a few dozen bytes.
    rows = store.materialise(_keyed(docs, F.struct(F.col(f"`{id_col}`").alias("id")), id_col, source_col, text_col, seed), "sizes")
    done = _taken(rows, _cuts(rows, weights, max_epochs), partial)
    return done.select(F.col("row.id").alias("doc_id"), "size", "source_size", "target", "taken", "repeats")


def _cuts(rows: DataFrame, weights, max_epochs: int) -> DataFrame:
    """(source, source_size, target, whole, rest, cut, before), one row a source: its whole repetitions, the words due
    beyond them, and the digest bucket in which these run out."""
    # Digest buckets are summed first, so a source's cut is known up to one bucket without sorting documents.
    buckets = store.materialise(rows.groupBy("source", "bucket").agg(F.sum("size").alias("words")), "buckets")
    targets = source_targets(buckets.groupBy("source").agg(F.sum("words").alias("source_size")), weights, max_epochs)
    due = F.floor(F.col("target") + 0.5).cast("long")
    targets = targets.withColumn("due", due).withColumn("whole", F.when(F.col("source_size") > 0, F.expr("due div source_size")).otherwise(F.lit(0)).cast("long"))
    targets = targets.withColumn("rest", F.col("due") - F.col("whole") * F.col("source_size")).drop("due", "weight")
    run = Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    cuts = buckets.withColumn("before", F.coalesce(F.sum("words").over(run), F.lit(0).cast("long")))
    same = F.col("t.source").eqNullSafe(F.col("c.source"))
    cuts = cuts.alias("c").join(targets.alias("t"), same).where("c.before <= t.rest and c.before + c.words > t.rest").select(F.col("t.source").alias("source"), F.col("c.bucket").alias("cut"), F.col("c.before").alias("before"))
    return store.materialise(targets.alias("t").join(cuts.alias("c"), same, "left").select("t.*", "c.cut", "c.before"), "cuts")


def _meet(rows: DataFrame, targets: DataFrame, broadcast_sources: int) -> DataFrame:
    """``rows`` with the columns of their source."""
    same = F.col("d.source").eqNullSafe(F.col("t.source"))
    own = ["source_size", "target", "whole", "rest", "cut", "before"]
    if targets.count() <= broadcast_sources:
        return rows.alias("d").join(F.broadcast(targets).alias("t"), same).select("d.*", *[f"t.{c}" for c in own])
    salted = targets.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    dealt = rows.withColumn("salt", F.pmod(F.xxhash64("digest"), F.lit(SALTS)).cast("int"))
    return dealt.alias("d").join(salted.alias("t"), same & (F.col("d.salt") == F.col("t.salt"))).select("d.*", *[f"t.{c}" for c in own]).drop("salt")


def _taken(rows: DataFrame, targets: DataFrame, partial: bool) -> DataFrame:
    """``rows`` with source_size, target, taken and repeats."""
    sized = _meet(rows, targets, BROADCAST_SOURCES)
    in_cut = F.coalesce(F.col("bucket") == F.col("cut"), F.lit(False))
    outside = sized.where(~in_cut).withColumn("extra", F.when(F.col("bucket") < F.coalesce("cut", F.lit("")), F.col("size")).otherwise(F.lit(0).cast("long")))
    walk = Window.partitionBy("source").orderBy("digest", "doc_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    inside = sized.where(in_cut).withColumn("left", F.col("rest") - F.col("before") - F.coalesce(F.sum("size").over(walk), F.lit(0).cast("long")))
    if partial:
        extra = F.greatest(F.lit(0).cast("long"), F.least("left", "size"))
    else:
        extra = F.when(2 * F.col("left") >= F.col("size"), F.col("size")).otherwise(F.lit(0).cast("long"))
    inside = inside.withColumn("extra", F.when(F.col("left") > 0, extra).otherwise(F.lit(0).cast("long"))).drop("left")
    both = outside.unionByName(inside)
    return both.select("row", "size", "source_size", "target", (F.col("whole") * F.col("size") + F.col("extra")).alias("taken"), (F.col("whole") + (F.col("extra") > 0).cast("long")).alias("repeats"))


def apply_mix(docs: DataFrame, id_col: str = "doc_id", source_col: str = "source", text_col: str = "text", weights=WEIGHTS, max_epochs: int = MAX_EPOCHS, seed: str = SEED) -> DataFrame:
    """The mixed corpus: each document's row as often as the mix takes it (whole documents only)."""
    rows = _keyed(docs, F.struct(*[F.col(f"`{c}`") for c in docs.columns]), id_col, source_col, text_col, seed)
    done = _taken(rows, _cuts(rows, weights, max_epochs), False).where("repeats > 0")
    each = done.select("row", F.explode(F.expr("sequence(1L, repeats)")))
    return each.select(*[F.col("row").getField(c).alias(c) for c in docs.columns])


def op8_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = store.table(spark, sf_dir, "documents")
    return plan_mix(docs).select("doc_id", "size", "source_size", "target", "taken")


OP8_SQL = r"""
with d as (select doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::bigint size,
                  md5('mix-7:' || coalesce(doc_id::varchar, 'null')) digest from documents),
s as (select source, sum(size)::bigint source_size from d group by source),
w as (select *, [5.0::double, 2.0::double, 1.0::double][((row_number() over (order by source is null, source) - 1) % 3 + 1)::int] weight,
             3 * source_size::double cap from s),
f as (select *, coalesce(sum(cap) over b, 0.0) uc, coalesce(sum(weight) over b, 0.0) uw,
             sum(source_size) over ()::double total, sum(weight) over () aw from w
      window b as (order by cap / weight, source is null, source rows between unbounded preceding and 1 preceding)),
l as (select min_by(lv, cap / weight) lv from (select *, (total - uc) / (aw - uw) lv from f) where lv * weight <= cap),
t as (select source, source_size, least(cap, weight * lv) target from w, l),
u as (select *, floor(target + 0.5)::bigint due, case when source_size > 0 then floor(target + 0.5)::bigint // source_size else 0 end whole from t),
r as (select d.doc_id, d.size, u.source_size, u.target, u.whole, u.due - u.whole * u.source_size rest,
             coalesce(sum(d.size) over (partition by d.source order by d.digest, d.doc_id, d.size rows between unbounded preceding and 1 preceding), 0)::bigint bef
      from d join u on d.source is not distinct from u.source)
select doc_id, size, source_size, target, (whole * size + greatest(0, least(rest - bef, size)))::bigint taken from r
"""
