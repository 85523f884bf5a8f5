"""Near-duplicate documents from bottom-k sketches made with one hash function.

1. Each document's distinct word shingles are hashed once; the ``k`` smallest values are its sketch.
   Documents with equal shingle sets form a class, and only the class with its smallest id goes on.
2. Inverted lists over sketch values, rarest first: two sets at the threshold share at least ``t`` sketch
   values, so sharing one among each one's ``s - t + 1`` globally rarest is necessary. Values found in
   one class only are counted, not listed, and very frequent ones fall off the end.
3. Stars: every member of a list is compared with the list's first member. Candidates pass the estimate
   from the union's sketch, then the exact ratio on full shingle sets.
4. Lists whose members are then still in several components are compared in blocks of bounded size,
   only across components. Their shingles that no other member has, and counts of the rest by hash
   bucket, bound what two of them can share; a pair is tried in one of its lists only; again estimate first, exact ratio after. No list is
   capped and copies never meet each other pair by pair.

For sets larger than ``k`` the bound ``t`` lies six standard deviations below the expected overlap (a
pair just at the threshold is missed with a probability below one in a million); smaller sets are exact.

Defined results: null, empty or blank text has no shingles and no links; a text with fewer words than the
shingle width is one shingle; a null id is never linked (its component is null, kept); repeated rows share
an id and so a component; ties (sets of equal size and values) are one class; a very long text is one sketch and one
set; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from math import ceil, floor, log, sqrt

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relseq.llm import store
from relseq.llm import text_kernels as tk

K = 64
BLOCK = 512
SIGNATURE = 128
PERCENT = 80


def shingle_sets(ids: pa.Array, texts: pa.Array, width: int) -> Iterator[tuple[int, np.ndarray]]:
    """(row, sorted distinct shingle hashes) for every row of a batch."""
    data, off = tk.buffers(texts)
    for lo, hi, part, cuts in tk.slices(data, off):
        words, bounds, _ = tk.word_hashes(part, cuts)
        values, ends = tk.shingle_hashes(words, bounds, width)
        for i in range(hi - lo):
            own = values[ends[i] : ends[i + 1]]
            if len(own) > 1:
                own = np.sort(own)
                own = own[np.concatenate(([True], own[1:] != own[:-1]))]
            yield lo + i, own


def sketches(docs: DataFrame, width: int, k: int = K) -> DataFrame:
    """(doc_id, n_shingles, fp1, fp2, sketch): set size, a 128-bit set fingerprint and the bottom-k values."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = np.zeros(batch.num_rows, np.int64)
            fp = np.zeros((2, batch.num_rows), np.uint64)
            low: list[np.ndarray] = []
            for row, own in shingle_sets(batch.column(0), batch.column(1), width):
                n[row] = len(own)
                fp[0, row], fp[1, row] = own.sum(dtype=np.uint64), tk.mix(own ^ tk.U(0xA5A5)).sum(dtype=np.uint64)
                low.append(own[:k])
            lengths = np.concatenate(([0], np.cumsum([len(x) for x in low]))).astype(np.int32)
            flat = np.concatenate([*low, np.zeros(0, np.uint64)]).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n), *(pa.array(f.view(np.int64)) for f in fp), pa.ListArray.from_arrays(pa.array(lengths), pa.array(flat))], ["doc_id", "n_shingles", "fp1", "fp2", "sketch"])

    return docs.mapInArrow(run, "doc_id long, n_shingles long, fp1 long, fp2 long, sketch array<long>")


def full_sets(docs: DataFrame, width: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [own.tobytes() for _, own in shingle_sets(batch.column(0), batch.column(1), width)]
            for at in range(0, len(found), 1000):
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(at, 1000), pa.array(found[at : at + 1000], pa.binary())], ["id", "members"])

    return docs.mapInArrow(run, "id long, members binary")


def least_overlap(size: int, k: int, percent: int) -> int:
    """Sketch values that any partner at the threshold shares with a set of ``size``, at least."""
    p = percent / 100
    if size < k:
        return max(1, min(ceil(p * size - 1e-9), floor(k - (1 - p) / p * k)))
    return max(1, floor(p * k - 6 * sqrt(k * p * (1 - p))))


def union_overlap(a: np.ndarray, b: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """For rows of two padded sketch tables: values of the union's sketch that both have, and its size."""
    both = np.sort(np.concatenate((a, b), axis=1), axis=1)
    real = both != np.iinfo(np.uint64).max
    again = np.zeros(both.shape, bool)
    again[:, 1:] = (both[:, 1:] == both[:, :-1]) & real[:, 1:]
    rank = np.cumsum(~again & real, axis=1)
    return (again & (rank <= k)).sum(axis=1), np.minimum(rank[:, -1], k)


def padded(column: pa.ListArray, k: int) -> np.ndarray:
    off = column.offsets.to_numpy()
    flat = column.values.to_numpy(zero_copy_only=False).view(np.uint64)
    out = np.full((len(column), k), np.iinfo(np.uint64).max, np.uint64)
    n = np.diff(off)
    cols = np.arange(off[-1] - off[0]) - np.repeat(off[:-1] - off[0], n)
    out[np.repeat(np.arange(len(column)), n), cols] = flat[off[0] : off[-1]]
    return out


def passes(a: np.ndarray, b: np.ndarray, k: int, percent: int) -> np.ndarray:
    shared, size = union_overlap(a, b, k)
    return np.where(size < k, 100 * shared >= percent * size, shared >= least_overlap(k, k, percent))


def first_common_kept(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The smallest value that both rows have with the low bit set (which marks listed values), halved."""
    both = np.sort(np.concatenate((a, b), axis=1), axis=1)
    hit = (both[:, 1:] == both[:, :-1]) & (both[:, 1:] & tk.U(1) == 1) & (both[:, 1:] != np.iinfo(np.uint64).max)
    return both[np.arange(len(both)), hit.argmax(axis=1)] >> tk.U(1)


def estimated(pairs: DataFrame, reps: DataFrame, k: int, percent: int) -> DataFrame:
    """The pairs (a, b) whose union sketch leaves the threshold possible."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ok = np.zeros(batch.num_rows, bool)
            for at in range(0, batch.num_rows, 4096):
                part = batch.slice(at, 4096)
                ok[at : at + 4096] = passes(padded(part.column(2), k), padded(part.column(3), k), k, percent)
            yield batch.select(["a", "b"]).filter(pa.array(ok))

    both = pairs.join(reps.select(F.col("rep").alias("a"), F.col("sketch").alias("sa")), "a").join(reps.select(F.col("rep").alias("b"), F.col("sketch").alias("sb")), "b")
    return both.select("a", "b", "sa", "sb").mapInArrow(run, "a long, b long")


def verified(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs whose full shingle sets reach the threshold."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ok = []
            for x, y in zip(batch.column(2), batch.column(3)):
                a, b = (np.frombuffer(v.as_buffer(), np.uint64) for v in (x, y))
                if 100 * min(len(a), len(b)) < percent * max(len(a), len(b)):
                    ok.append(False)
                    continue
                both = np.sort(np.concatenate((a, b)))
                common = int((both[1:] == both[:-1]).sum())
                ok.append(100 * common >= percent * (len(both) - common))
            yield batch.select(["a", "b"]).filter(pa.array(ok, pa.bool_()))

    both = pairs.join(sets.select(F.col("id").alias("b"), F.col("members").alias("mb")), "b").join(sets.select(F.col("id").alias("a"), F.col("members").alias("ma")), "a")
    return both.select("a", "b", "ma", "mb").mapInArrow(run, "a long, b long")


def components(edges: DataFrame) -> DataFrame:
    """(v, comp) for every vertex of an edge table: the smallest vertex reachable. Labels move along edges
    and then jump to their own label, so the rounds grow with the logarithm of a chain's length."""
    both = store.materialise(edges.select("a", "b").union(edges.select(F.col("b"), F.col("a"))).distinct(), "edges", few=True)
    labels = store.materialise(both.groupBy(F.col("a").alias("v")).agg(F.least(F.min("b"), F.col("v")).alias("comp")).withColumn("old", F.col("v")), "labels", few=True)
    while labels.where("old <> comp").limit(1).count():
        now = labels.select("v", "comp")
        near = both.join(now.select(F.col("v").alias("b"), "comp"), "b").groupBy(F.col("a").alias("v")).agg(F.min("comp").alias("near"))
        step = now.join(near, "v").select("v", F.col("comp").alias("old"), F.least("comp", "near").alias("comp"))
        jump = step.select(F.col("v").alias("comp"), F.col("comp").alias("further"))
        labels = store.materialise(step.join(jump, "comp").select("v", F.least("comp", "further").alias("comp"), "old"), "labels", few=True)
    return labels.select("v", "comp")


def cross_pairs(members: DataFrame, k: int, percent: int, block: int = BLOCK) -> DataFrame:
    """Candidate pairs across components inside each list. ``members(value, rep, n, m, sig, comp, sketch)``:
    ``m`` and ``sig`` bound overlaps, and the low bits of the sketch mark the values listed.

    Lists are dealt into blocks by a hash, and two blocks meet in one task-sized group, whatever the list's length.
    """
    lists = store.materialise(members.groupBy("value").agg(F.count("*").alias("n"), F.ceil(F.count("*") / block).cast("int").alias("blocks")), "blocks", few=True)
    total = lists.agg(F.sum("n")).first()[0] or 0
    counted = store.with_groups(members.withColumnRenamed("n", "size"), lists, ["value"], total).withColumnRenamed("size", "n")
    cut = counted.withColumn("i", F.pmod(F.xxhash64("rep"), F.col("blocks")).cast("int"))
    sent = cut.withColumn("o", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    sent = sent.select("value", F.least("i", "o").alias("lo"), F.greatest("i", "o").alias("hi"), "i", "rep", "n", "m", "sig", "comp", "sketch")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: pa.Table | None = None
        for batch in batches:
            table = pa.Table.from_batches([batch])
            held = table if held is None else pa.concat_tables([held, table])
            keys = [held.column(c).to_numpy() for c in ("value", "lo", "hi")]
            change = np.flatnonzero(np.logical_or.reduce([x[1:] != x[:-1] for x in keys])) + 1
            if len(change):
                yield from compare(held.slice(0, int(change[-1])), np.concatenate(([0], change)))
                held = held.slice(int(change[-1]))
        if held is not None and held.num_rows:
            yield from compare(held, np.array([0, held.num_rows]))

    def compare(table: pa.Table, cuts: np.ndarray) -> Iterator[pa.RecordBatch]:
        rep, n, m, comp, i, value = (table.column(c).to_numpy() for c in ("rep", "n", "m", "comp", "i", "value"))
        sketch = padded(table.column("sketch").combine_chunks(), k)
        sig = np.frombuffer(b"".join(x.as_py() for x in table.column("sig")), np.uint32).reshape(-1, SIGNATURE)
        plain = np.where(sketch == np.iinfo(np.uint64).max, sketch, sketch >> tk.U(1))
        lo, hi = table.column("lo").to_numpy(), table.column("hi").to_numpy()
        left: list[np.ndarray] = []
        right: list[np.ndarray] = []
        waiting = 0

        def flush() -> Iterator[pa.RecordBatch]:
            x, y = np.concatenate(left), np.concatenate(right)
            for at in range(0, len(x), 4096):
                p, q = x[at : at + 4096], y[at : at + 4096]
                most = np.minimum(sig[p], sig[q]).sum(axis=1, dtype=np.int64)
                ok = 100 * most >= percent * (n[p] + n[q] - most)
                p, q = p[ok], q[ok]
                if not len(p):
                    continue
                ok = first_common_kept(sketch[p], sketch[q]) == value[p].view(np.uint64) >> tk.U(1)
                p, q = p[ok], q[ok]
                ok = passes(plain[p], plain[q], k, percent)
                a, b = rep[p[ok]], rep[q[ok]]
                yield pa.RecordBatch.from_arrays([pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b))], ["a", "b"])

        for begin, end in zip(cuts[:-1], cuts[1:]):
            if end - begin < 2:
                continue
            if lo[begin] == hi[begin]:
                x, y = np.triu_indices(end - begin, 1)
                x, y = x + begin, y + begin
            else:
                own = np.arange(begin, end)
                first, second = own[i[begin:end] == lo[begin]], own[i[begin:end] == hi[begin]]
                x, y = np.repeat(first, len(second)), np.tile(second, len(first))
            most = np.minimum(m[x], m[y])  # no pair shares more, and sets of n and n' that share s have n + n' - s
            ok = (comp[x] != comp[y]) & (100 * most >= percent * (n[x] + n[y] - most)) & (100 * np.minimum(n[x], n[y]) >= percent * np.maximum(n[x], n[y]))
            if ok.any():
                left.append(x[ok])
                right.append(y[ok])
                waiting += int(ok.sum())
            if waiting > 65536:
                yield from flush()
                left, right, waiting = [], [], 0
        if waiting:
            yield from flush()

    keys = ["value", "lo", "hi"]
    return sent.repartition(*keys).sortWithinPartitions(*keys).mapInArrow(run, "a long, b long")


def overlap_bounds(sets: DataFrame) -> DataFrame:
    """(rep, m, sig): how many of a set's shingles some other of ``sets`` has too, in all and by hash bucket. What two
    sets share is at most the smaller of their counts, summed over buckets."""

    def flat(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for rep, cell in zip(batch.column(0), batch.column(1)):
                values = np.frombuffer(cell.as_buffer(), np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(values), rep.as_py())), pa.array(values)], ["rep", "value"])

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            m, sig = [], []
            for cell, alone in zip(batch.column(1), batch.column(2)):
                own = np.bincount((np.frombuffer(cell.as_buffer(), np.uint64) & tk.U(SIGNATURE - 1)).astype(np.int64), minlength=SIGNATURE)
                if alone.is_valid:
                    own = own - np.bincount(alone.values.to_numpy(), minlength=SIGNATURE)
                m.append(int(own.sum()))
                sig.append(own.astype(np.uint32).tobytes())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(m, pa.int64()), pa.array(sig, pa.binary())], ["rep", "m", "sig"])

    single = sets.select("id", "members").mapInArrow(flat, "rep long, value long").groupBy("value").agg(F.count("*").alias("m"), F.min("rep").alias("id")).where("m = 1")
    bucket = F.col("value").bitwiseAND(F.lit(SIGNATURE - 1).cast("long")).cast("int")
    alone = single.groupBy("id").agg(F.collect_list(bucket).alias("alone"))  # at most a set's own size
    return sets.join(alone, "id", "left").select("id", "members", "alone").mapInArrow(count, "rep long, m long, sig binary")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 5, percent: int = PERCENT, k: int = K) -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id, kept."""
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    every = store.materialise(sketches(texts, width, k), "sketches")
    some = every.where("n_shingles > 0 and doc_id is not null")
    classes = some.groupBy("fp1", "fp2", "n_shingles").agg(F.min("doc_id").alias("rep"), F.first("sketch").alias("sketch"))
    reps = store.materialise(classes.withColumnRenamed("n_shingles", "n"), "classes")

    # Rarest values of each sketch among those that more than one class has.
    listed = reps.select("rep", "n", F.explode("sketch").alias("value"))
    shared = listed.groupBy("value").agg(F.count("*").alias("df")).where("df > 1")
    sizes = list(range(k + 1))
    table = F.array(*[F.lit(least_overlap(s, k, percent) if s else 1) for s in sizes])
    held = F.least(F.col("n"), F.lit(k)).cast("int")
    prefix = held - F.element_at(table, held + 1) + 1
    own = listed.join(shared, "value").groupBy("rep", "n").agg(F.collect_list(F.struct("df", "value")).alias("own"))
    room = prefix - (held - F.size("own"))  # values of one class only come first
    kept = own.where(room > 0).select("rep", "n", F.explode(F.slice(F.sort_array("own"), 1, F.greatest(room, F.lit(1)))).alias("x")).select("x.value", "rep", "n")
    kept = kept.withColumn("c", F.floor(F.log(F.col("n").cast("double")) / log(100 / percent + 1e-9)).cast("int"))
    kept = store.materialise(kept, "lists")

    first = kept.groupBy("value", "c").agg(F.min("rep").alias("a"), F.count("*").alias("m")).where("m > 1").drop("m")
    stars = kept.join(first, ["value", "c"]).where("rep <> a").select("a", F.col("rep").alias("b")).distinct()
    stars = store.materialise(estimated(stars, reps, k, percent), "stars", few=True)
    several = kept.groupBy("value").agg(F.count("*").alias("m")).where("m > 1").select("value")
    wanted = kept.join(several, "value", "left_semi").select(F.col("rep").alias("doc_id")).distinct()
    sets = store.materialise(full_sets(texts.join(wanted, "doc_id", "left_semi"), width), "sets", "none")
    links = store.materialise(verified(stars, sets, percent), "links", few=True)

    labels = components(links)
    placed = kept.join(labels.withColumnRenamed("v", "rep"), "rep", "left").withColumn("comp", F.coalesce("comp", "rep"))
    mixed = placed.groupBy("value").agg(F.min("comp").alias("x"), F.max("comp").alias("y")).where("x <> y").select("value")
    members = store.materialise(placed.join(mixed, "value", "left_semi").select("value", "rep", "n", "comp"), "members", few=True)
    asked = members.select("rep").distinct()
    bounds = overlap_bounds(sets.join(asked.withColumnRenamed("rep", "id"), "id", "left_semi"))
    # At most a sketch's worth of listed values for each member; they are marked in its sketch.
    marks = kept.join(asked, "rep", "left_semi").groupBy("rep").agg(F.collect_set("value").alias("listed"))
    marked = F.transform("sketch", lambda v: v.bitwiseAND(F.lit(-2).cast("long")).bitwiseOR(F.array_contains("listed", v).cast("long")))
    about = marks.join(reps, "rep").join(bounds, "rep").select("rep", "m", "sig", marked.alias("sketch"))
    crossing = store.materialise(cross_pairs(members.join(about, "rep").select("value", "rep", "n", "m", "sig", "comp", "sketch"), k, percent), "crossing", few=True)
    more = store.materialise(verified(crossing, sets, percent), "links", few=True)
    if more.limit(1).count():
        labels = components(links.union(more))

    by_class = reps.select("fp1", "fp2", F.col("n").alias("n_shingles"), "rep").join(labels.withColumnRenamed("v", "rep"), "rep", "left")
    by_class = by_class.select("fp1", "fp2", "n_shingles", F.coalesce("comp", "rep").alias("component"))
    out = every.drop("sketch").join(by_class, ["fp1", "fp2", "n_shingles"], "left")
    component = F.when(F.col("n_shingles") > 0, F.coalesce("component", "doc_id")).otherwise(F.col("doc_id"))
    out = out.select("doc_id", "n_shingles", F.when(F.col("doc_id").isNotNull(), component).alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def op6_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(store.table(spark, sf_dir, "documents"), width=4)
