"""Stage 2: from the occurrences of a skeleton to patterns over the taxonomies.

An occurrence's leaf row has a concept in every slot. A refinement is a *vector*: a concept or the root for
each slot, covering the occurrences whose leaf concepts lie at or below it; its support is the number of
sequences with a covered occurrence. Itemsets of (slot, ancestor) that are closed or maximal hold one chain
per slot and so are such vectors, and the search runs over vectors directly.

``grouped``: one search per skeleton, where the occurrences counted in stage 1 fit a task. ``partitioned``, for
any size: each chunk of sequences is searched with the threshold scaled down to it, which finds every vector
that is frequent in all (it is frequent in some chunk); those that the chunks' counts leave possible are counted
exactly where no count of them is known. Nothing but the result's own counts comes together, and nothing is
gathered on the driver.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import replace
from functools import cached_property
from itertools import islice
from math import ceil

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from relseq.functions import taxonomy
from relseq.functions.relations import oriented
from relseq.operators import dense, patterns
from relseq.operators.corpus import concept_view, condensed, looked_up, slot_names
from relseq.operators.matching import permuted
from relseq.operators.typemining import Mined
from relseq.session import ship

GROUP_LIMIT = 1_000_000  # occurrences of one skeleton that a task may hold
DENSE_LIMIT = 8_000_000  # the same where they are held as numbers and bits
CHUNK_ROWS = 400_000
VECTOR_BLOCK = 5_000  # candidates that meet a chunk at a time
LEAF = "skeleton string, seq_id string, leaf array<string>"
VECTORS = "skeleton string, vector array<string>, support long"


def leaf_rows(mined: Mined, permute: bool = False) -> DataFrame:
    """(skeleton, seq_id, leaf): distinct leaf rows of each sequence; equal ones do not change any support.
    Relations are resolved here, for matched pairs only, inside the sequence's own row. ``permute`` also takes the
    orders in which events of one type in one transaction can fill a skeleton. Rows of condensed sequences have their
    ``weight``."""
    weighted = ["weight"] if "weight" in mined.rows.columns else []
    relate = looked_up if weighted and mined.corpus.relations else oriented(list(mined.corpus.relations))
    if permute:
        k = max((len(patterns.parse(s)[0]) for s in mined.skeletons), default=1)
        more = F.flatten(F.transform("found", lambda o: F.transform(permuted(F.col("events"), o["lambda"], k), lambda lam: F.struct(o["skeleton"].alias("skeleton"), lam.alias("lambda")))))
        mined = replace(mined, rows=mined.rows.withColumn("found", more))
    made = F.transform("found", lambda o: F.struct(o["skeleton"].alias("skeleton"), concept_view(F.col("events"), o["lambda"], relate, mined.corpus.with_concepts).alias("leaf")))
    return mined.rows.select(F.col("seq_id").cast("string").alias("seq_id"), F.explode(F.array_distinct(made)).alias("x"), *weighted).select("x.skeleton", "seq_id", "x.leaf", *weighted)


def items(leafs: DataFrame) -> DataFrame:
    """(skeleton, seq_id, slot, concept): non-root ancestors of every leaf concept with their slot."""
    slots = leafs.select("skeleton", "seq_id", F.posexplode("leaf").alias("slot", "c"))
    return slots.select("skeleton", "seq_id", (F.col("slot") + 1).alias("slot"), F.explode(taxonomy.ancestors(F.col("c"))).alias("concept"))


def item_support(leafs: DataFrame) -> DataFrame:
    """(skeleton, slot, concept, support) over sequences."""
    return items(leafs).distinct().groupBy("skeleton", "slot", "concept").agg(F.count("*").alias("support"))


def approximate_item_support(leafs: DataFrame, error: float = 0.02) -> DataFrame:
    """The same by a sketch of the sequences of each item: no exchange of distinct pairs, for a first look."""
    return items(leafs).groupBy("skeleton", "slot", "concept").agg(F.approx_count_distinct("seq_id", error).alias("support"))


def support_cube(leafs: DataFrame, mined_total: int) -> DataFrame:
    """(skeleton, slot, depth, concepts, best_support, best_pct): frequent concepts summed up by every grouping of
    skeleton, slot and depth."""
    own = item_support(leafs).withColumn("depth", F.size(F.split("concept", "/")))
    return own.cube("skeleton", "slot", "depth").agg(F.count("*").alias("concepts"), F.max("support").alias("best_support")).withColumn("best_pct", F.round(100 * F.col("best_support") / mined_total, 4))


def vocabulary(leafs: DataFrame) -> DataFrame:
    """(skeleton, item_id, slot, concept, support), numbered by slot and concept."""
    return item_support(leafs).withColumn("item_id", F.row_number().over(Window.partitionBy("skeleton").orderBy("slot", "concept")))


def numbered(leafs: DataFrame) -> DataFrame:
    """Leaf rows with an ``occurrence`` number. Numbers of a partition follow each other, so their bitmaps are dense;
    store or persist the result before it is used twice."""
    return leafs.withColumn("occurrence", F.monotonically_increasing_id())


def matrix(leafs: DataFrame, layout: str = "rows") -> DataFrame:
    """The occurrence-by-item matrix, sparse: item ids of each occurrence, or for each item bitmaps of the occurrences
    (of ``numbered`` leaf rows) that have it, by bucket of occurrence numbers."""
    ids = vocabulary(leafs).select("skeleton", "slot", "concept", "item_id")
    occ = leafs if "occurrence" in leafs.columns else numbered(leafs)
    long = occ.select("skeleton", "seq_id", "occurrence", F.posexplode("leaf").alias("slot", "c")).select("skeleton", "seq_id", "occurrence", (F.col("slot") + 1).alias("slot"), F.explode(taxonomy.ancestors(F.col("c"))).alias("concept"))
    long = long.join(ids, ["skeleton", "slot", "concept"])
    if layout == "rows":
        return long.groupBy("skeleton", "seq_id", "occurrence").agg(F.array_sort(F.collect_set("item_id")).alias("items"))
    return long.groupBy("skeleton", "item_id", F.bitmap_bucket_number("occurrence").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("occurrence")).alias("bits"))


def bitmap_support(bitmaps: DataFrame, occ: DataFrame, skeleton: str, item_ids: list[int]) -> int:
    """Sequences with an occurrence that has all the items: the items' bitmaps are joined bit by bit, and the set bits
    lead back to sequences. ``occ`` are the ``numbered`` leaf rows that the bitmaps were made of."""
    own = bitmaps.where(F.col("skeleton") == skeleton).where(F.col("item_id").isin(item_ids))
    both = own.groupBy("bucket").agg(F.collect_list("bits").alias("all"), F.count("*").alias("n")).where(F.col("n") == len(set(item_ids)))  # one entry an item
    at = F.bitmap_bit_position("occurrence")
    byte = lambda b: F.conv(F.hex(F.substring(b, (at / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
    bit = lambda b: F.floor(byte(b) / F.pow(F.lit(2), at % 8)) % 2 == 1
    rows = occ.where(F.col("skeleton") == skeleton).withColumn("bucket", F.bitmap_bucket_number("occurrence"))
    return rows.join(both, "bucket").where(F.forall("all", bit)).select("seq_id").distinct().count()


def cover(leafs: DataFrame, vector: list[str]) -> DataFrame:
    """The leaf rows that a vector covers."""
    return leafs.where(taxonomy.subsumes_all(F.array(*[F.lit(c) for c in vector]), F.col("leaf")))


def support(leafs: DataFrame, vector: list[str]) -> int:
    return cover(leafs, vector).select("seq_id").distinct().count()


# -- search ---------------------------------------------------------------------------------------------------


def coded(rows: list[list[str]] | pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, list[str]]:
    """Leaf rows as numbers of names, and the names."""
    flat = pa.array(rows, pa.list_(pa.string())) if isinstance(rows, list) else rows.combine_chunks() if isinstance(rows, pa.ChunkedArray) else rows
    flat = pa.concat_arrays(flat.chunks) if isinstance(flat, pa.ChunkedArray) else flat
    words = flat.flatten().dictionary_encode()
    names = ["None" if w is None else w for w in words.dictionary.to_pylist()]
    indices = words.indices
    if indices.null_count:
        indices = indices.fill_null(len(names))
        names.append("None")
    return indices.to_numpy(zero_copy_only=False).reshape(len(flat), len(flat[0]) if len(flat) else 0), names


class Gathered:
    """Leaf rows of one skeleton that come batch by batch, held as numbers."""

    def __init__(self) -> None:
        self.names: dict[str, int] = {}
        self.seen: dict[str, int] = {}
        self.parts: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []  # sequences, leaf rows, weights

    def add(self, seq_ids: pa.Array, rows: pa.Array, weights: pa.Array) -> None:
        table, names = coded(rows)
        to = np.array([self.names.setdefault(n, len(self.names)) for n in names], np.int32)
        ids = seq_ids.dictionary_encode()
        of = np.array([self.seen.setdefault(x, len(self.seen)) for x in ids.dictionary.to_pylist()], np.int32)
        self.parts.append((of[ids.indices.to_numpy()], to[table] if table.size else table.astype(np.int32), weights.to_numpy()))

    def leaves(self) -> Leaves:
        sequences, rows, weights = (np.concatenate(x) for x in zip(*self.parts))
        return Leaves(sequences, (rows, list(self.names)), weights)


class Leaves:
    """Leaf rows of one skeleton, slot by slot as codes of leaf concepts, with the codes below each node. Rows of a
    sequence stand together; ``weights`` (of rows) say for how many sequences a sequence stands."""

    def __init__(self, sequences: np.ndarray, rows: list[list[str]] | pa.Array | pa.ChunkedArray | tuple[np.ndarray, list[str]], weights: np.ndarray | None = None) -> None:
        order = np.argsort(sequences, kind="stable")
        self.sequences = sequences[order]
        self.weights = np.ones(len(order), np.int64) if weights is None else weights[order]
        self.codes: list[np.ndarray] = []
        self.below: list[dict[str, np.ndarray]] = []  # node -> is a code at or below it?
        self.children: list[dict[str, list[str]]] = []
        table, names = rows if isinstance(rows, tuple) else coded(rows)
        wide = table.shape[1]
        table = table[order]
        for s in range(wide):
            own, code = np.unique(table[:, s], return_inverse=True)
            code = code.astype(np.int32 if len(own) > 30_000 else np.int16)
            flags: dict[str, np.ndarray] = {}
            kids: dict[str, list[str]] = {}
            for i, n in enumerate(own):
                for c in taxonomy.climb(names[n]):
                    flags.setdefault(c, np.zeros(len(own), bool))[i] = True
            for c in flags:
                kids.setdefault(c.rpartition("/")[0], []).append(c)
            self.codes.append(np.ascontiguousarray(code))
            self.below.append(flags)
            self.children.append({k: sorted(v) for k, v in kids.items()})

    @cached_property
    def slots(self) -> list[dict[str, np.ndarray]]:
        """Node masks over all rows."""
        return [{c: flags[code] for c, flags in own.items()} for own, code in zip(self.below, self.codes)]

    def under(self, rows: np.ndarray, slot: int, concept: str) -> np.ndarray:
        """Those of the rows (by number) that lie at or below a concept."""
        flags = self.below[slot].get(concept)
        return rows[:0] if flags is None else rows[flags[self.codes[slot][rows]]]

    def support(self, mask: np.ndarray) -> int:
        return self.support_of(np.flatnonzero(mask))

    def support_of(self, rows: np.ndarray) -> int:
        own = self.sequences[rows]
        return int(self.weights[rows[:1]].sum() + self.weights[rows[1:][own[1:] != own[:-1]]].sum())


def frequent_vectors(leaves: Leaves, theta: int) -> dict[tuple[str, ...], int]:
    """Every vector with at least ``theta`` sequences: slots are fixed from the left, each by descending its
    tree as long as the support lasts. Only the rows still covered are looked at."""
    wide = len(leaves.codes)
    out: dict[tuple[str, ...], int] = {}

    def fill(s: int, chosen: tuple[str, ...], rows: np.ndarray, count: int) -> None:
        if s == wide:
            out[chosen] = count
            return
        fill(s + 1, (*chosen, taxonomy.ROOT), rows, count)
        todo = [(c, rows) for c in leaves.children[s].get(taxonomy.ROOT, [])]
        while todo:
            c, above = todo.pop()
            own = leaves.under(above, s, c)
            n = leaves.support_of(own)
            if n >= theta:
                fill(s + 1, (*chosen, c), own, n)
                todo += [(d, own) for d in leaves.children[s].get(c, [])]

    whole = np.arange(len(leaves.sequences))
    n = leaves.support_of(whole)
    if n >= theta:
        fill(0, (), whole, n)
    return out


def maximal_vectors(leaves: Leaves, theta: int) -> dict[tuple[str, ...], int]:
    """Those of ``frequent_vectors`` of which none is one step narrower. Vectors are held as bytes, a few for a slot;
    every frequent one marks those one step broader, which are frequent too."""
    wide = len(leaves.codes)
    names = [[taxonomy.ROOT, *sorted(flags)] for flags in leaves.below]
    size = 1 if max(map(len, names), default=0) <= 256 else 4
    ids = [{c: i.to_bytes(size, "little") for i, c in enumerate(own)} for own in names]
    parent = [{ids[s][c]: ids[s].get(c.rpartition("/")[0], ids[s][taxonomy.ROOT]) for c in own[1:]} for s, own in enumerate(names)]
    place: dict[bytes, int] = {}
    counts: list[int] = []

    def fill(s: int, chosen: bytes, rows: np.ndarray, count: int) -> None:
        if s == wide:
            place[chosen] = len(counts)
            counts.append(count)
            return
        fill(s + 1, chosen + ids[s][taxonomy.ROOT], rows, count)
        todo = [(c, rows) for c in leaves.children[s].get(taxonomy.ROOT, [])]
        while todo:
            c, above = todo.pop()
            own = leaves.under(above, s, c)
            n = leaves.support_of(own)
            if n >= theta:
                fill(s + 1, chosen + ids[s][c], own, n)
                todo += [(d, own) for d in leaves.children[s].get(c, [])]

    whole = np.arange(len(leaves.sequences))
    n = leaves.support_of(whole)
    if n >= theta:
        fill(0, b"", whole, n)
    covered = bytearray(len(counts))
    slots = [(s, s * size, (s + 1) * size) for s in range(wide)]
    for v in place:
        for s, a, b in slots:
            up = parent[s].get(v[a:b])
            if up is not None:
                covered[place[v[:a] + up + v[b:]]] = 1
    return {tuple(names[s][int.from_bytes(v[a:b], "little")] for s, a, b in slots): counts[i] for v, i in place.items() if not covered[i]}


def maximal_itemsets(leaves: Leaves, theta: int) -> dict[tuple[str, ...], int]:
    """Maximal vectors by backtracking over items: the head grows by items in ascending order of support, a
    branch ends when head and tail together lie inside a known maximal set, and deeper calls see only the
    known sets that still matter."""
    items = [(s, c, m) for s, masks in enumerate(leaves.slots) for c, m in masks.items()]
    items = [(leaves.support(m), s, c, m) for s, c, m in items]
    items = sorted((x for x in items if x[0] >= theta), key=lambda x: (x[0], x[1], x[2]))
    whole = np.ones(len(leaves.sequences), bool)
    if leaves.support(whole) < theta:
        return {}
    found: list[frozenset[int]] = []

    def walk(head: frozenset[int], mask: np.ndarray, tail: list[int], known: list[frozenset[int]]) -> None:
        alive = []
        for i in tail:
            own = mask & items[i][3]
            n = leaves.support(own)
            if n >= theta:
                alive.append((n, i, own))
        alive.sort(key=lambda x: (x[0], x[1]))
        if not alive:
            if not any(head <= k for k in known):
                found.append(head)
                known.append(head)
            return
        start = len(found)
        for at, (_, i, own) in enumerate(alive):
            rest = [j for _, j, _ in alive[at + 1 :]]
            near = [k for k in [*known, *found[start:]] if i in k]
            if any((head | {i} | set(rest)) <= k for k in near):
                continue
            walk(head | {i}, own, rest, near)
        for k in found[start:]:
            known.append(k)

    walk(frozenset(), whole, list(range(len(items))), [])
    best = [k for k in set(found) if not any(k < o for o in found)]
    out = {}
    for k in best:
        vector = [taxonomy.ROOT] * len(leaves.codes)
        mask = whole
        for i in k:
            _, s, c, m = items[i]
            mask = mask & m
            if c.count("/") >= vector[s].count("/") and len(c) > len(vector[s]):
                vector[s] = c
        out[tuple(vector)] = leaves.support(mask)
    return out


def levelwise_itemsets(leaves: Leaves, theta: int, most: int | None = None) -> dict[frozenset[tuple[int, str]], int]:
    """All frequent itemsets by joining sets that share all but one item: the textbook way, exponential."""
    masks = {(s, c): m for s, own in enumerate(leaves.slots) for c, m in own.items()}
    level = {frozenset([i]): m for i, m in masks.items() if leaves.support(m) >= theta}
    out = {k: leaves.support(m) for k, m in level.items()}
    size = 1
    while level and (most is None or size < most):
        size += 1
        nxt: dict[frozenset, np.ndarray] = {}
        by_rest: dict[frozenset, list] = {}
        for k in level:
            for i in k:
                by_rest.setdefault(k - {i}, []).append(i)
        for rest, ends in by_rest.items():
            for x in range(len(ends)):
                for y in range(x + 1, len(ends)):
                    k = rest | {ends[x], ends[y]}
                    if k not in nxt and all(k - {i} in level for i in k):
                        m = level[k - {ends[x]}] & masks[ends[x]]
                        if leaves.support(m) >= theta:
                            nxt[k] = m
        out |= {k: leaves.support(m) for k, m in nxt.items()}
        level = nxt
    return out


def itemset_vector(itemset, wide: int) -> tuple[str, ...]:
    """The deepest concept of each slot, the root where a slot has none."""
    out = [taxonomy.ROOT] * wide
    for s, c in itemset:
        if len(c) > len(out[s]):
            out[s] = c
    return tuple(out)


def _grouped(leafs: DataFrame, theta: int, algorithm: str) -> DataFrame:
    search = {"vectors": frequent_vectors, "maximal": maximal_vectors, "backtrack": maximal_itemsets}.get(algorithm)

    def found_in(leaves: Leaves) -> dict[tuple[str, ...], int]:
        if algorithm != "levelwise":
            return search(leaves, theta)
        whole = leaves.support(np.ones(len(leaves.sequences), bool))
        sets = {frozenset(): whole} | levelwise_itemsets(leaves, theta)
        return {itemset_vector(k, len(leaves.codes)): n for k, n in sets.items()}

    def report(name: str, gathered: Gathered) -> Iterator[pa.RecordBatch]:
        found = iter(found_in(gathered.leaves()).items())
        while part := list(islice(found, VECTOR_BLOCK)):
            yield pa.RecordBatch.from_arrays([pa.array([name] * len(part), pa.string()), pa.array([list(v) for v, _ in part], pa.list_(pa.string())), pa.array([n for _, n in part], pa.int64())], ["skeleton", "vector", "support"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come by skeleton."""
        name, gathered = None, Gathered()
        for batch in batches:
            skeletons = batch.column(0).to_numpy(zero_copy_only=False)
            cuts = [0, *(np.flatnonzero(skeletons[1:] != skeletons[:-1]) + 1).tolist(), len(skeletons)]
            for a, b in zip(cuts, cuts[1:]):
                if a == b:
                    continue
                if gathered.parts and skeletons[a] != name:
                    yield from report(name, gathered)
                    gathered = Gathered()
                name = skeletons[a]
                part = batch.slice(a, b - a)
                gathered.add(part.column(1), part.column(2), part.column(3))
        if gathered.parts:
            yield from report(name, gathered)

    rows = _weighted(leafs).select("skeleton", F.col("seq_id").cast("string").alias("seq_id"), "leaf", "weight")
    return rows.repartition("skeleton").sortWithinPartitions("skeleton").mapInArrow(run, VECTORS)


def _weighted(leafs: DataFrame) -> DataFrame:
    return leafs if "weight" in leafs.columns else leafs.withColumn("weight", F.lit(1).cast("long"))


def _chunks(batches: Iterator[pa.RecordBatch], most: int) -> Iterator[pa.Table]:
    """Whole sequences, about ``most`` leaf rows at a time; a small rest joins the chunk before it."""
    held: list[pa.RecordBatch] = []
    rows = 0
    before: pa.Table | None = None
    for batch in batches:
        held.append(batch)
        rows += batch.num_rows
        if rows >= most:
            table = pa.Table.from_batches(held)
            seq = table.column("seq_id").to_numpy(zero_copy_only=False)
            cut = int(np.flatnonzero(seq != seq[-1])[-1]) + 1 if (seq != seq[-1]).any() else 0
            if cut:
                if before is not None:
                    yield before
                before = table.slice(0, cut)
                rest = table.slice(cut)
                held, rows = rest.to_batches(), rest.num_rows
    if rows and before is not None and 2 * rows < most:
        before = pa.concat_tables([before, pa.Table.from_batches(held)])
    elif rows:
        if before is not None:
            yield before
        before = pa.Table.from_batches(held)
    if before is not None:
        yield before


def _leaves(table: pa.Table) -> Leaves:
    return Leaves(table.column("seq").to_numpy(), table.column("leaf"), table.column("weight").to_numpy())


def _packed_chunks(leafs: DataFrame, most: int) -> DataFrame:
    """(skeleton, sequences, leaves): the leaf rows of one skeleton in one chunk of sequences, as one value."""
    schema = pa.schema([("seq", pa.int32()), ("leaf", pa.list_(pa.string())), ("weight", pa.int64())])

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in _chunks(batches, most):
            names = table.column("skeleton").to_numpy(zero_copy_only=False).astype(str)
            _, first, seq = np.unique(table.column("seq_id").to_numpy(zero_copy_only=False).astype(str), return_index=True, return_inverse=True)
            number = int(table.column("weight").to_numpy()[first].sum())
            for skeleton in np.unique(names):
                own = np.flatnonzero(names == skeleton)
                part = pa.Table.from_arrays([pa.array(seq[own].astype(np.int32)), table.column("leaf").take(pa.array(own)), table.column("weight").take(pa.array(own))], schema=schema)
                sink = pa.BufferOutputStream()
                with pa.ipc.new_stream(sink, schema) as writer:
                    writer.write_table(part)
                yield pa.RecordBatch.from_arrays([pa.array([str(skeleton)]), pa.array([number], pa.int64()), pa.array([sink.getvalue().to_pybytes()], pa.binary())], ["skeleton", "sequences", "leaves"])

    return _weighted(leafs).mapInArrow(pack, "skeleton string, sequences long, leaves binary")


def _partitioned(leafs: DataFrame, theta: int, total: int, together: bool = False) -> DataFrame:
    """``together``: the rows of a sequence stand side by side in one partition already; if not, they are brought
    there, since a sequence in two chunks would be counted twice.

    What a chunk finds comes with its count there. A chunk that does not report a vector has fewer sequences of it
    than the chunk's threshold, which bounds the support from above: vectors below ``theta`` even so are dropped, the
    others are counted in the chunks that did not report them. Chunks and blocks of candidates meet by skeleton.
    """
    if not together:
        leafs = leafs.repartition("seq_id").sortWithinPartitions("seq_id")
    chunks = _packed_chunks(leafs, CHUNK_ROWS).persist()
    # Sequences without any occurrence are in no chunk, so the chunk's share can only be too high.
    least = lambda n: max(1, ceil(theta * n / total - 1e-9))
    least_of = F.greatest(F.lit(1), F.ceil(F.col("sequences") * theta / total - 1e-9))

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                found = frequent_vectors(_leaves(pa.ipc.open_stream(row["leaves"]).read_all()), least(row["sequences"]))
                if found:
                    n = len(found)
                    yield pa.RecordBatch.from_arrays([pa.array([row["skeleton"]] * n), pa.array([list(v) for v in found], pa.list_(pa.string())), pa.array(list(found.values()), pa.int64()), pa.array([least(row["sequences"]) - 1] * n, pa.int64())], ["skeleton", "vector", "support", "slack"])

    reported = chunks.mapInArrow(local, "skeleton string, vector array<string>, support long, slack long").persist()
    room = chunks.groupBy("skeleton").agg(F.sum(least_of - 1).cast("long").alias("room"), F.count("*").alias("chunks"))
    summed = reported.groupBy("skeleton", "vector").agg(F.sum("support").alias("support"), F.sum("slack").alias("slack"), F.count("*").alias("seen"))
    possible = summed.join(room, "skeleton").where(F.col("support") + F.col("room") - F.col("slack") >= theta)
    done = possible.where("seen = chunks").select("skeleton", "vector", "support")
    open_ = possible.where("seen < chunks").select("skeleton", "vector")
    # One row a skeleton, and their number does not depend on the data.
    many = F.broadcast(open_.groupBy("skeleton").agg(F.ceil(F.count("*") / VECTOR_BLOCK).alias("blocks")))
    dealt = open_.join(many, "skeleton").withColumn("block", F.pmod(F.xxhash64("vector"), "blocks"))
    blocks = dealt.groupBy("skeleton", "block").agg(F.collect_list("vector").alias("vectors"))  # about VECTOR_BLOCK

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                leaves = _leaves(pa.ipc.open_stream(row["leaves"]).read_all())
                vectors, counts = [], []
                for v in row["vectors"]:
                    own = np.arange(len(leaves.sequences))
                    for s, c in enumerate(v):
                        if c:
                            own = leaves.under(own, s, c)
                    if n := leaves.support_of(own):
                        vectors.append(v)
                        counts.append(n)
                if vectors:
                    yield pa.RecordBatch.from_arrays([pa.array([row["skeleton"]] * len(vectors)), pa.array(vectors, pa.list_(pa.string())), pa.array(counts, pa.int64())], ["skeleton", "vector", "support"])

    counted = chunks.select("skeleton", "leaves").join(blocks, "skeleton").select("skeleton", "leaves", "vectors").mapInArrow(count, VECTORS)
    counted = counted.groupBy("skeleton", "vector").agg(F.sum("support").alias("support")).where(F.col("support") >= theta)
    return done.where(F.col("support") >= theta).unionByName(counted)


def broader(vector) -> object:
    """Column: the vectors one step more general, one slot lifted to its parent."""
    return F.filter(F.transform(F.sequence(F.lit(0), F.size(vector) - 1), lambda s: F.transform(vector, lambda c, i: F.when(i == s, F.when(c == "", F.lit(None)).otherwise(taxonomy.parent(c))).otherwise(c))), lambda v: ~F.exists(v, lambda c: c.isNull()))


def keep(vectors: DataFrame, kind: str) -> DataFrame:
    """``all``; ``maximal``: no frequent vector is one step narrower; ``closed``: none of equal support is."""
    if kind == "all":
        return vectors
    vectors = vectors.persist()  # found once, used twice
    wide = F.size("vector") > 0
    above = vectors.where(wide).select("skeleton", F.explode(broader(F.col("vector"))).alias("vector"), F.col("support").alias("s"))
    if kind == "maximal":
        return vectors.join(above.select("skeleton", "vector").distinct(), ["skeleton", "vector"], "left_anti")
    if kind == "closed":
        best = above.groupBy("skeleton", "vector").agg(F.max("s").alias("best"))
        return vectors.join(best, ["skeleton", "vector"], "left").where(F.col("best").isNull() | (F.col("best") < F.col("support"))).drop("best")
    raise ValueError("kind is all, closed or maximal")


def refine_any(leafs: DataFrame, theta: int, kind: str = "maximal", algorithm: str = "vectors", total: int | None = None, largest: int | None = None, together: bool = False) -> DataFrame:
    """(skeleton, vector, support) for any table (skeleton, seq_id, leaf): the second stage by itself, for
    patterns of other structures too. ``largest``: rows of the largest skeleton, if known. ``together``: rows of a
    sequence stand side by side."""
    ship(leafs.sparkSession)
    if algorithm in ("backtrack", "levelwise"):
        found = _grouped(leafs, theta, algorithm)
        return found if algorithm == "backtrack" and kind == "maximal" else keep(found.distinct().groupBy("skeleton", "vector").agg(F.max("support").alias("support")), kind)
    if largest is None:
        largest = max((r["count"] for r in leafs.groupBy("skeleton").count().orderBy(F.desc("count")).limit(1).collect()), default=0)
    if algorithm == "partitioned" or largest > GROUP_LIMIT:
        if total is None:
            total = _weighted(leafs).groupBy("seq_id").agg(F.max("weight").alias("n")).agg(F.sum("n")).first()[0] or 0
        found = _partitioned(leafs, theta, total, together)
    elif kind == "maximal":
        return _grouped(leafs, theta, "maximal")
    else:
        found = _grouped(leafs, theta, "vectors")
    return keep(found, kind)


def refine(mined: Mined, kind: str = "maximal", algorithm: str = "vectors", scope: str = "skeleton", permute: bool = False) -> DataFrame:
    """(skeleton, vector, support) of every frequent skeleton's refinements. ``scope="global"`` also compares
    refinements of different skeletons."""
    largest = max((n for _, n in mined.skeletons.values()), default=0)
    if kind == "maximal" and algorithm == "vectors" and not permute and mined.limits and min(largest, mined.stored or largest) <= DENSE_LIMIT:
        found = _dense(mined)
        return globally_maximal(mined, found) if scope == "global" else found
    if mined.grow and not permute and "weight" not in mined.rows.columns:
        mined = replace(mined, rows=mined.grow(condensed(mined.corpus, mined.timed).sequences))
    if largest > GROUP_LIMIT and "weight" in mined.rows.columns:
        largest = mined.stored or None  # rows of condensed sequences are fewer
    found = refine_any(leaf_rows(mined, permute), mined.threshold, kind, algorithm, mined.total, largest, together=True)  # leaf rows come out of their sequence's row
    return globally_maximal(mined, found) if scope == "global" else found


def _dense(mined: Mined) -> DataFrame:
    ship(mined.rows.sparkSession)
    corpus = mined.corpus
    if "weight" not in corpus.sequences.columns:
        corpus = condensed(corpus, mined.timed)
        corpus = replace(corpus, sequences=corpus.sequences.persist())  # read twice
    wide = {s: len(slot_names(list(patterns.parse(s)[0]), corpus.trees, corpus.relations, corpus.with_concepts)) for s in mined.skeletons}
    return dense.refined(corpus, mined.skeletons, mined.threshold, mined.total, mined.limits, wide)


def globally_maximal(mined: Mined, refined: DataFrame) -> DataFrame:
    """Of refinements of all skeletons, those that no refinement with one event more says as much as: dropping an
    event of the longer one leaves the shorter one or something narrower. Layouts are one row a skeleton."""
    corpus = mined.corpus
    cuts = []
    for text in mined.skeletons:
        s = patterns.parse(text)
        names = slot_names(list(s[0]), corpus.trees, corpus.relations, corpus.with_concepts)
        for i in range(len(s[0]) if len(s[0]) > 1 else 0):
            touched = [n for n, name in enumerate(names) if str(i + 1) in name.partition(".")[0].split("-")]
            cuts.append((text, patterns.render(patterns.drop(s, i)), [n for n in range(len(names)) if n not in touched]))
    spark = refined.sparkSession
    table = F.broadcast(spark.createDataFrame(cuts, "skeleton string, shorter string, left array<int>"))
    longer = refined.join(table, "skeleton").select(F.col("shorter"), F.transform("left", lambda i: F.get("vector", i)).alias("narrow")).distinct()
    covered = refined.join(longer, (F.col("skeleton") == F.col("shorter")) & taxonomy.subsumes_all(F.col("vector"), F.col("narrow")), "left_semi")
    return refined.join(covered.select("skeleton", "vector").distinct(), ["skeleton", "vector"], "left_anti")


def to_patterns(mined: Mined, refined: DataFrame) -> DataFrame:
    """(skeleton, pattern, n_events, support, support_pct, specialised): refinements with their text. A pattern is
    specialised if an event concept of it lies below the root."""
    corpus = mined.corpus
    about = []
    for s in mined.skeletons:
        p = patterns.parse(s)
        names = slot_names(list(p[0]), corpus.trees, corpus.relations, corpus.with_concepts)
        about.append((s, len(p[0]), list(p[0]), [bool(b) for b in p[1]], names))
    # One row for each frequent skeleton.
    table = F.broadcast(refined.sparkSession.createDataFrame(about, "skeleton string, n_events int, types array<string>, breaks array<boolean>, slots array<string>"))
    rows = refined.join(table, "skeleton")
    filled = F.filter(F.zip_with("slots", "vector", lambda n, c: F.struct(n.alias("n"), c.alias("c"))), lambda x: x["c"] != "")
    where = lambda x: F.substring_index(x["n"], ".", 1)

    def known(i):
        own = F.filter("known", lambda x: F.substring_index(where(x), "-", -1).cast("int") == i)
        return F.transform(own, lambda x: F.concat(x["c"], F.when(F.contains(x["n"], F.lit("-")), F.concat(F.lit(" to "), F.substring_index(where(x), "-", 1))).otherwise("")))

    def shown(t, i):
        return F.concat(F.when(i == 0, "").when(F.get("breaks", i - 1), " ; ").otherwise(" "), t, F.when(F.size(known(i + 1)) > 0, F.concat(F.lit("("), F.array_join(known(i + 1), ", "), F.lit(")"))).otherwise(""))

    rows = rows.withColumn("known", filled)
    text = F.array_join(F.transform("types", shown), "")
    special = F.exists("known", lambda x: ~F.contains(x["n"], F.lit("-")))
    return rows.select("skeleton", text.alias("pattern"), "n_events", "support", F.round(100 * F.col("support") / mined.total, 4).alias("support_pct"), special.alias("specialised"), "vector")


def match(mined_or_leafs: DataFrame, skeleton: str, vector: list[str]) -> DataFrame:
    """Sequences in which one refinement occurs."""
    own = mined_or_leafs.where(F.col("skeleton") == skeleton)
    return cover(own, vector).select("seq_id").distinct()
