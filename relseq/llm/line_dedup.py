"""Repeated runs of lines, found in a suffix order over line-ID sequences by distributed prefix doubling.

A document is the sequence of its non-blank lines; documents of equal text are one sequence from the start. Round 0
names each line that occurs more than once by its rank among all lines (the number of positions with a smaller
name, so equal ranks are one interval of the suffix order). A doubling round names windows of twice the length by
the pair of ranks at a position and at the position one window further; positions whose window is unique leave, and
rounds go on until every window is unique.

Equal ranks at a window length are an interval of the suffix order whose longest common prefix is at least that
length. Its first member (smallest id, then place) stays, every other member begins a later copy of that many
lines. The later copies of all rounds cover just the repeated runs of every length, since a run between two powers
is covered by its first and last window of the smaller power; covered lines are deleted. A run counts from
``min_lines`` lines on, or as one line if that has ``min_words`` words.

Windows never cross documents and are judged on the input, not on what is left of it. A name is a 128-bit
hash in round 0 and exact ranks after it. Very frequent names are joined apart: at most ``store.HOT_GROUPS`` of them can
hold that share of all positions, so theirs is a small table, and the positions stay where they are.

Defined results: null text is empty text; blank lines are never deleted and do not separate runs; a document
has to have two different places for a run to be repeated inside it; rows with equal id and text are
one document (both keep the same lines); a null id sorts before all others; an empty table stays empty; a very
long text is one sequence, and its marks are one row; other columns are kept as they are.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StringType, StructField, StructType

from relseq.llm import store

MIN_LINES = 2
MIN_WORDS = 50
LINE_END = "\n"
WORD = r"[^\x20\x09-\x0D]+"
BLANK = "\x20\x09\x0a\x0b\x0c\x0d"


def line_ids(docs: DataFrame, id_col: str, text_col: str, min_words: int) -> DataFrame:
    """(k1, k2, k3, lines): a document's key (k1 its id, k2 and k3 of its text) and its non-blank lines' names,
    each with whether the line counts as a run by itself."""
    text = F.coalesce(F.col(f"`{text_col}`"), F.lit(""))
    rows = docs.select(key_of_id(id_col), F.xxhash64(text).alias("k2"), F.xxhash64(F.lit(7), text).alias("k3"), text.alias("text"))
    full = F.filter(F.split("text", LINE_END), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    # Words are counted only where there is room for that many.
    long = lambda x: (F.length(x) >= 2 * min_words - 1) & (F.regexp_count(x, F.lit(WORD)) >= min_words)
    return rows.select("k1", "k2", "k3", F.transform(full, lambda x: F.struct(F.xxhash64(x).alias("h1"), F.xxhash64(F.lit(7), x).alias("h2"), long(x).alias("long"))).alias("lines"))


def key_of_id(id_col: str):
    return F.coalesce(F.col(f"`{id_col}`").cast("long"), F.lit(-(2**63)).cast("long")).alias("k1")


def positions(ids: DataFrame) -> DataFrame:
    """(k1, k2, seq, long, h1, h2): the lines of one document for each different text, the one with the smallest id."""
    once = ids.groupBy("k2", "k3").agg(F.min("k1").alias("k1"), F.first("lines").alias("lines"))
    return once.select("k1", "k2", F.posexplode("lines").alias("seq", "x")).select("k1", "k2", "seq", "x.long", "x.h1", "x.h2")


def global_ranks(groups: DataFrame, keys: list[str]) -> tuple[DataFrame, int]:
    """``groups`` with ``rank``, the sum of ``n`` over groups whose keys sort before, and the sum of all. Range-
    partitioned; one total for each partition comes to the driver."""
    ordered = groups.repartitionByRange(*keys).withColumn("__p", F.spark_partition_id())
    ordered = store.materialise(ordered, "ranks")
    totals = {r["__p"]: r["t"] for r in ordered.groupBy("__p").agg(F.sum("n").alias("t")).collect()}
    base, total = [], 0
    for p, n in sorted(totals.items()):
        base.append((p, total))
        total += n
    before = Window.partitionBy("__p").orderBy(*keys).rowsBetween(Window.unboundedPreceding, -1)
    bases = groups.sparkSession.createDataFrame(pa.table({"__p": pa.array([p for p, _ in base], pa.int32()), "base": pa.array([n for _, n in base], pa.int64())}))  # a row for each partition
    ranked = ordered.withColumn("local", F.coalesce(F.sum("n").over(before), F.lit(0))).join(F.broadcast(bases), "__p")
    return ranked.withColumn("rank", F.col("local") + F.col("base")).drop("__p", "local", "base"), total


def levels(lines: DataFrame, min_lines: int) -> Iterator[tuple[int, DataFrame]]:
    """(window length, (k1, k2, seq, long, rank, f1, f2, f3)): the positions of every window of that many lines that
    occurs again, its interval's rank and the place of the interval's first member, until none does. Lengths
    double from 1 on, but take in ``min_lines``."""
    size, keys, now = 1, ["h1", "h2"], lines
    while True:
        first = F.min(F.struct("k1", "k2", "seq")).alias("first")
        groups, total = global_ranks(now.groupBy(*keys).agg(F.count("*").alias("n"), first).where("n > 1"), keys)
        if not total:
            return
        step = min(size, min_lines - size) if size < min_lines else size
        # The rank of the window one step further in the same document, if that occurs again too.
        further = Window.partitionBy("k1", "k2").orderBy("seq").rangeBetween(step, step)
        named = store.with_groups(now, groups, keys, total).withColumn("r2", F.max("rank").over(further))
        named = store.materialise(named.select("k1", "k2", "seq", "long", "rank", "r2", F.col("first.k1").alias("f1"), F.col("first.k2").alias("f2"), F.col("first.seq").alias("f3")), "windows")
        yield size, named.drop("r2")
        now = named.where("r2 is not null").select("k1", "k2", "seq", "long", F.col("rank").alias("r1"), "r2")
        keys, size = ["r1", "r2"], size + step


LATER = "not (k1 = f1 and k2 = f2 and seq = f3)"


def suffix_order(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(k1, k2, seq, length, rank): ``length`` is the longest window of a power of two lines that starts here and occurs
    again (so the longest common prefix with another suffix is at least that and less than twice that), and
    ``rank`` its place in the suffix order at that length. Of equal texts the one with the smallest id is told."""
    ids = store.materialise(line_ids(docs, id_col, text_col, MIN_WORDS), "lines")
    out = docs.sparkSession.createDataFrame([], "k1 long, k2 long, seq int, length int, rank long")
    for size, named in levels(positions(ids), 1):
        out = out.unionByName(named.select("k1", "k2", "seq", F.lit(size).alias("length"), "rank"))
    return out.groupBy("k1", "k2", "seq").agg(F.max_by(F.struct("length", "rank"), "length").alias("x")).select("k1", "k2", "seq", "x.length", "x.rank")


def repeated_runs(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_lines: int = MIN_LINES) -> DataFrame:
    """(k1, seq, lines, f1, fseq): maximal runs of non-blank lines that repeat the run at (f1, fseq), the earliest place
    of each of their windows; neighbouring windows whose earliest places are neighbours too are one run. Of equal
    texts the one with the smallest id is told."""
    ids = store.materialise(line_ids(docs, id_col, text_col, MIN_WORDS), "lines")
    found = next((named for size, named in levels(positions(ids), min_lines) if size == min_lines), None)
    if found is None:
        return docs.sparkSession.createDataFrame([], "k1 long, seq int, lines long, f1 long, fseq int")
    along = Window.partitionBy("k1", "k2", "f1", "f2", F.col("f3") - F.col("seq")).orderBy("seq")
    isle = found.where(LATER).withColumn("isle", F.col("seq") - F.row_number().over(along))
    runs = isle.groupBy("k1", "k2", "f1", "f2", (F.col("f3") - F.col("seq")).alias("shift"), "isle").agg(F.min("seq").alias("seq"), F.count("*").alias("n"))
    return runs.select("k1", "seq", (F.col("n") + (min_lines - 1)).alias("lines"), "f1", (F.col("seq") + F.col("shift")).alias("fseq"))


def removed_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_lines: int = MIN_LINES, min_words: int = MIN_WORDS) -> DataFrame:
    """(k1, k2, whole, spans): for each document that loses lines either ``whole`` (an earlier document has the same
    text) or the later copies in it, as (first non-blank line, how many)."""
    ids = store.materialise(line_ids(docs, id_col, text_col, min_words), "lines")
    texts = ids.groupBy("k2", "k3").agg(F.count("*").alias("n"), F.min("k1").alias("first")).where("n > 1")
    texts = store.materialise(texts, "texts")
    copies = texts.agg(F.sum("n")).first()[0] or 0
    same = store.with_groups(ids.select("k1", "k2", "k3"), texts, ["k2", "k3"], copies).where("k1 > first").select("k1", "k2").distinct()
    out = same.select("k1", "k2", F.lit(True).alias("whole"), F.expr("cast(array() as array<struct<seq: int, size: int>>)").alias("spans"))
    later = None
    for size, named in levels(positions(ids), min_lines):
        own = named.where(LATER if size >= min_lines else f"long and {LATER}").select("k1", "k2", "seq", F.lit(size).alias("size"))
        later = own if later is None else later.unionByName(own)
    if later is None:
        return out
    # A document's own lines: bounded by its text, which is one value anyway.
    spans = later.groupBy("k1", "k2").agg(F.collect_list(F.struct("seq", "size")).alias("spans"))
    return out.unionByName(spans.select("k1", "k2", F.lit(False).alias("whole"), "spans"))


def dedupe_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_lines: int = MIN_LINES, drop_emptied: bool = True, min_words: int = MIN_WORDS) -> DataFrame:
    """The documents without later copies of repeated line runs, columns as they came. Documents of which
    nothing but blank lines is left go, unless they came so."""
    out = with_removals(docs, id_col, text_col, min_lines, min_words)
    if drop_emptied:
        out = out.where((F.col("removed") == 0) | F.col("left").rlike(r"[^\x20\x09-\x0D]"))
    own = {c: F.col("row").getField(c) for c in docs.columns}
    own[text_col] = F.when(F.col("removed") > 0, F.col("left")).otherwise(own[text_col])
    return out.select(*[x.alias(c) for c, x in own.items()])


def kept_text(text: str, whole: bool, spans: np.ndarray, min_lines: int, min_words: int) -> tuple[str, int, int]:
    """What is left of a text, and how many lines in how many runs went."""
    lines = text.split(LINE_END)
    full = [i for i, x in enumerate(lines) if x.strip(BLANK)]
    if whole:
        gone = np.full(len(full), len(full) >= min_lines)
        if not gone.any():
            gone[:] = [len(re.findall(WORD, lines[i])) >= min_words for i in full]
    else:
        edge = np.zeros(len(full) + 1, np.int64)
        np.add.at(edge, spans[:, 0], 1)
        np.add.at(edge, spans[:, 0] + spans[:, 1], -1)
        gone = np.cumsum(edge[:-1]) > 0
    out = {full[i] for i in np.flatnonzero(gone).tolist()}
    runs = int(np.count_nonzero(np.diff(gone.astype(np.int8), prepend=0) == 1))
    return LINE_END.join([x for i, x in enumerate(lines) if i not in out]), len(out), runs


def with_removals(docs: DataFrame, id_col: str, text_col: str, min_lines: int, min_words: int) -> DataFrame:
    """(row, left, removed, runs): each row as a struct, what is left of its text, and how many lines in how many
    runs went."""
    gone = removed_lines(docs, id_col, text_col, min_lines, min_words).select(F.col("k1").alias("r1"), F.col("k2").alias("r2"), "whole", "spans")
    key2 = F.xxhash64(F.coalesce(F.col(f"`{text_col}`"), F.lit("")))
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), key_of_id(id_col), key2.alias("k2"))
    own = rows.join(gone, (F.col("k1") == F.col("r1")) & (F.col("k2") == F.col("r2")), "left").select("row", "whole", "spans")

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            spans = batch.column(2)
            ends = spans.offsets.to_numpy()
            each = spans.values
            pairs = np.stack((each.field("seq").to_numpy(), each.field("size").to_numpy()), axis=1)
            done = [
                kept_text(text.as_py() or "", whole, pairs[ends[i] : ends[i + 1]], min_lines, min_words)
                for i, (text, whole) in enumerate(zip(batch.column(0).field(text_col), batch.column(1).to_pylist()))
            ]
            left, removed, runs = zip(*done) if done else ((), (), ())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(left, pa.string()), pa.array(removed, pa.int64()), pa.array(runs, pa.int64())], ["row", "left", "removed", "runs"])

    schema = StructType([own.schema["row"], StructField("left", StringType()), StructField("removed", LongType()), StructField("runs", LongType())])
    zero = F.lit(0).cast("long")
    untouched = own.where("whole is null").select("row", F.coalesce(F.col("row").getField(text_col), F.lit("")).alias("left"), zero.alias("removed"), zero.alias("runs"))
    return own.where("whole is not null").mapInArrow(cut, schema).unionByName(untouched)


def op4_line_run_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = store.table(spark, sf_dir, "documents").select("doc_id", "text")
    out = with_removals(docs, "doc_id", "text", MIN_LINES, MIN_WORDS)
    lines = F.size(F.split(F.coalesce("row.text", F.lit("")), LINE_END)).cast("long")
    return out.select("row.doc_id", lines.alias("n_lines"), F.col("removed").alias("n_removed"), F.col("runs").alias("n_runs"), F.sha2("left", 256).alias("kept_sha256"))


OP4_SQL = r"""
with d as (select doc_id, string_split(coalesce(text, ''), chr(10)) ls from documents),
e as (select doc_id, unnest(ls) ln, generate_subscripts(ls, 1) - 1 line from d),
f as (select doc_id, ln, line, row_number() over (partition by doc_id order by line) seq from e where regexp_matches(ln, '[^\x20\x09-\x0D]')),
p as (select doc_id, seq, ln, lead(ln) over (partition by doc_id order by seq) nx from f),
w as (select doc_id, seq, (doc_id, seq) > min((doc_id, seq)) over (partition by ln, nx) late from p where nx is not null),
o as (select doc_id, seq, ln, (doc_id, seq) > min((doc_id, seq)) over (partition by ln) late from f),
g as (select doc_id, seq from w where late union select doc_id, seq + 1 from w where late
      union select doc_id, seq from o where late and len(regexp_extract_all(ln, '[^\x20\x09-\x0D]+')) >= 50),
m as (select g.doc_id, g.seq, f.line, g.seq - row_number() over (partition by g.doc_id order by g.seq) isle from g join f using (doc_id, seq)),
r as (select doc_id, count(*) n, count(distinct isle) runs from m group by doc_id),
k as (select e.doc_id, string_agg(e.ln, chr(10) order by e.line) kept from e left join m using (doc_id, line) where m.line is null group by e.doc_id)
select d.doc_id, len(ls)::bigint n_lines, coalesce(r.n, 0)::bigint n_removed, coalesce(r.runs, 0)::bigint n_runs, sha256(coalesce(k.kept, '')) kept_sha256
from d left join r using (doc_id) left join k using (doc_id)
"""
