"""Nearest neighbours by a hierarchical navigable small-world graph per shard.

Vectors are dealt, by their length and then by a hash of their id, to shards of bounded size. Each shard builds one
graph over its distinct directions, kept as flat arrays (vectors, fixed-width neighbour tables, member ids), and is
stored as one row of them. Queries go to every shard of their length in blocks; a shard answers with its best few,
scored by the exact cosine, and the answers are merged by score and id.

A node is a direction: vectors that are multiples of each other are one node that lists its ids in order, so a shard
full of copies is still a graph of distinct points. All members have the score of the one with the smallest id, and
ties, within a node and between nodes, go to the smaller id: every reached node that ties with the last place takes
part in the order.

Defined results: a vector that is null, empty, zero, or has a null or non-finite component takes no part; a cosine is
between vectors of equal length only, so those of another length are no candidates; a query is never its own
neighbour; rows repeated under one id with the same vector are one candidate, with other vectors each is one; fewer
candidates than asked for give all that a graph reaches; an empty table gives none; very long vectors make smaller
shards; other columns are ignored.
"""

from __future__ import annotations

from heapq import heappop, heappush

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from relseq.llm import store

SHARD_ROWS = 16_384
SHARD_BYTES = 64 << 20  # of a shard's vectors as doubles, at most
LINKS = 16
BUILD_WIDTH = 64
SEARCH_WIDTH = 200
QUERY_EVERY = 50
TOP = 5
QUERY_BLOCK = 4096
SAME_DIRECTION = 12  # decimals of unit vectors that agree


class Graph:
    """Layered graph over unit vectors. ``links[level]`` is an int32 table, -1 for no neighbour."""

    def __init__(self, points: np.ndarray, links: int = LINKS, width: int = BUILD_WIDTH, seed: int = 11) -> None:
        self.points, self.m = points, links
        n = len(points)
        draw = np.random.default_rng(seed)
        self.level = np.minimum((-np.log(1 - draw.random(n)) / np.log(links)).astype(np.int32), 8)
        self.links = [np.full((n, links * (2 if lv == 0 else 1)), -1, np.int32) for lv in range(int(self.level.max(initial=0)) + 1)]
        self.sizes = [np.zeros(n, np.int32) for _ in self.links]
        self.entry, self.top = 0, int(self.level[0]) if n else 0
        for i in range(1, n):
            self._insert(i, width)

    def _insert(self, i: int, width: int) -> None:
        q, at = self.points[i], self.entry
        for lv in range(self.top, int(self.level[i]), -1):
            at = self._greedy(q, at, lv)
        entries = [at]
        for lv in range(min(self.top, int(self.level[i])), -1, -1):
            found = self._beam(q, entries, lv, width)
            for j in self._pick(found, self.m):
                self._join(i, j, lv)
                self._join(j, i, lv)
            entries = [j for _, j in found]
        if self.level[i] > self.top:
            self.top, self.entry = int(self.level[i]), i

    def _join(self, a: int, b: int, lv: int) -> None:
        table, sizes = self.links[lv], self.sizes[lv]
        n = sizes[a]
        if n < table.shape[1]:
            table[a, n] = b
            sizes[a] += 1
            return
        all_of = np.append(table[a], b)
        far = 1 - self.points[all_of] @ self.points[a]
        order = np.argsort(far, kind="stable")
        keep = self._pick(list(zip(far[order].tolist(), all_of[order].tolist())), table.shape[1])
        table[a] = -1
        table[a, : len(keep)] = keep
        sizes[a] = len(keep)

    def _pick(self, found: list[tuple[float, int]], most: int) -> list[int]:
        """Nearest first, leaving out those nearer to a chosen one than to the point; filled up by nearness."""
        if len(found) <= most:
            return [j for _, j in found]
        found = found[: 3 * most]
        ids = np.array([j for _, j in found])
        between = 1 - self.points[ids] @ self.points[ids].T
        chosen: list[int] = []
        for k, (d, _) in enumerate(found):
            if len(chosen) == most:
                break
            if not chosen or between[k, chosen].min() >= d:
                chosen.append(k)
        taken = set(chosen)
        chosen += [k for k in range(len(found)) if k not in taken][: most - len(chosen)]
        return ids[chosen].tolist()

    def _greedy(self, q: np.ndarray, at: int, lv: int) -> int:
        best = float(self.points[at] @ q)
        while True:
            near = self.links[lv][at, : self.sizes[lv][at]]
            if not len(near):
                return at
            close = self.points[near] @ q
            k = int(close.argmax())
            if close[k] <= best:
                return at
            best, at = float(close[k]), int(near[k])

    def _beam(self, q: np.ndarray, entries: list[int], lv: int, width: int) -> list[tuple[float, int]]:
        """The ``width`` nearest points reached, as (distance, point), nearest first."""
        seen = np.zeros(len(self.points), bool)
        seen[entries] = True
        start = 1 - self.points[entries] @ q
        todo: list[tuple[float, int]] = []
        best: list[tuple[float, int]] = []
        for d, j in zip(start.tolist(), entries):
            heappush(todo, (d, j))
            heappush(best, (-d, j))
        while len(best) > width:
            heappop(best)
        links, sizes = self.links[lv], self.sizes[lv]
        while todo:
            d, j = heappop(todo)
            if len(best) >= width and d > -best[0][0]:
                break
            near = links[j, : sizes[j]]
            near = near[~seen[near]]
            if not len(near):
                continue
            seen[near] = True
            far = 1 - self.points[near] @ q
            if len(best) >= width:
                ok = far < -best[0][0]
                near, far = near[ok], far[ok]
            for e, k in zip(far.tolist(), near.tolist()):
                if len(best) < width:
                    heappush(best, (-e, k))
                elif e < -best[0][0]:
                    heappop(best)
                    heappush(best, (-e, k))
                else:
                    continue
                heappush(todo, (e, k))
        return sorted((-d, j) for d, j in best)

    def search(self, q: np.ndarray, width: int) -> list[int]:
        at = self.entry
        for lv in range(self.top, 0, -1):
            at = self._greedy(q, at, lv)
        return [j for _, j in self._beam(q, [at], 0, width)]


def usable(vectors: DataFrame, id_col: str, vector_col: str) -> DataFrame:
    """(vec_id, v array<double>) of the rows that take part."""
    v = F.transform(F.col(vector_col), lambda x: x.cast("double"))
    rows = vectors.select(F.col(id_col).cast("long").alias("vec_id"), v.alias("v")).where("vec_id is not null and v is not null")
    fine = F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return rows.where(fine & F.exists("v", lambda x: x != 0)).dropDuplicates(["vec_id", "v"])


def shard_counts(rows: DataFrame, shard_rows: int = SHARD_ROWS) -> DataFrame:
    """(dim, shards): a row for each length of vectors."""
    most = F.greatest(F.lit(1), F.least(F.lit(shard_rows), F.expr(f"cast({SHARD_BYTES} div (8 * dim) as int)")))
    return rows.groupBy(F.size("v").alias("dim")).agg(F.count("*").alias("n")).select("dim", (1 + F.floor(F.col("n") / most)).cast("int").alias("shards"))


def _matrix(column) -> np.ndarray:
    """Rows, all of one length, as doubles."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    flat = column.values.to_numpy(zero_copy_only=False)[column.offsets[0].as_py() : column.offsets[-1].as_py()]
    return flat.reshape(len(column), -1).astype(float) if len(column) else np.zeros((0, 0))


def _units(points: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Unit vectors and lengths; scaled by the largest component first, so that no square over- or underflows."""
    top = np.abs(points).max(axis=1, keepdims=True)
    scaled = points / top
    size = np.linalg.norm(scaled, axis=1, keepdims=True)
    return scaled / size, (size * top)[:, 0]


GRAPH = "dim int, shard int, points binary, unit binary, links array<binary>, sizes array<binary>, entry int, top int, ids binary, ends binary"


def build(rows: DataFrame, counts: DataFrame) -> DataFrame:
    """A row of flat arrays for each shard with vectors. ``counts(dim, shards)``."""

    def make(table: pa.Table) -> pa.Table:
        ids = table.column("vec_id").to_numpy()
        order = np.argsort(ids, kind="stable")
        ids, points = ids[order], _matrix(table.column("v"))[order]
        unit = _units(points)[0]
        # The first member, the one with the smallest id, stands for the direction.
        _, first, node = np.unique(np.round(unit, SAME_DIRECTION) + 0.0, axis=0, return_index=True, return_inverse=True)
        node = node.ravel()
        by_node = np.argsort(node, kind="stable")
        ends = np.concatenate(([0], np.cumsum(np.bincount(node, minlength=len(first)))))
        graph = Graph(unit[first].astype(np.float32))
        raw = {"points": points[first], "unit": graph.points, "ids": ids[by_node], "ends": ends.astype(np.int64)}
        cells = {k: [x.tobytes()] for k, x in raw.items()}
        lists = {"links": [[x.tobytes() for x in graph.links]], "sizes": [[x.tobytes() for x in graph.sizes]]}
        row = {"dim": [points.shape[1]], "shard": [table.column("shard")[0].as_py()], **cells, **lists, "entry": [graph.entry], "top": [graph.top]}
        types = {"dim": pa.int32(), "shard": pa.int32(), "entry": pa.int32(), "top": pa.int32(), "links": pa.list_(pa.binary()), "sizes": pa.list_(pa.binary())}
        names = [x.split(" ")[0] for x in GRAPH.split(", ")]
        return pa.table({k: pa.array(row[k], types.get(k, pa.binary())) for k in names})

    dealt = rows.withColumn("dim", F.size("v")).join(counts, "dim").withColumn("shard", F.pmod(F.xxhash64("vec_id"), F.col("shards")).cast("int"))
    # A graph is minutes of work on few bytes, which must not be taken for a reason to put shards together.
    shards = counts.agg(F.sum("shards")).first()[0] or 1
    return dealt.repartition(2 * shards, "dim", "shard").groupBy("dim", "shard").applyInArrow(make, GRAPH)


def _load(row: dict) -> tuple[Graph, np.ndarray, np.ndarray, np.ndarray]:
    """Graph, its nodes' original vectors, member ids and their bounds by node."""
    dim = row["dim"]
    points = np.frombuffer(row["points"]).reshape(-1, dim)
    graph = Graph.__new__(Graph)
    graph.points, graph.m, graph.entry, graph.top = np.frombuffer(row["unit"], np.float32).reshape(-1, dim), LINKS, row["entry"], row["top"]
    graph.links = [np.frombuffer(x, np.int32).reshape(len(points), -1) for x in row["links"]]
    graph.sizes = [np.frombuffer(x, np.int32) for x in row["sizes"]]
    return graph, points, np.frombuffer(row["ids"], np.int64), np.frombuffer(row["ends"], np.int64)


def search(graphs: DataFrame, queries: DataFrame, counts: DataFrame, top: int = TOP, width: int = SEARCH_WIDTH, block: int = QUERY_BLOCK) -> DataFrame:
    """(query_id, rank, vec_id, score). ``queries(vec_id, v)`` go to all shards of their length in blocks of about ``block``."""
    blocks = 1 + queries.count() // block
    # A block stands once for each shard; the rows it adds are the stated query set against every shard.
    blocked = queries.withColumn("dim", F.size("v")).withColumn("block", F.pmod(F.xxhash64(F.lit(3), "vec_id"), F.lit(blocks)).cast("int"))
    sent = blocked.join(counts, "dim").withColumn("shard", F.explode(F.sequence(F.lit(0), F.col("shards") - 1))).drop("shards")

    def find(left: pa.Table, right: pa.Table) -> pa.Table:
        out_q, out_v, out_s = [], [], []
        if left.num_rows and right.num_rows:
            graph, points, ids, ends = _load(left.slice(0, 1).to_pylist()[0])
            units, _ = _units(points)
            asked, _ = _units(_matrix(right.column("v")))
            for q, v in zip(right.column("vec_id").to_pylist(), asked):
                near = np.array(graph.search(v.astype(np.float32), min(width, max(1, len(points)))))
                score = units[near] @ v
                order = np.argsort(-score, kind="stable")
                best: list[tuple[float, int]] = []
                last = None
                for k in order.tolist():
                    if last is not None and score[k] < last:
                        break
                    lo, hi = int(ends[near[k]]), int(ends[near[k] + 1])
                    best += [(-float(score[k]), j) for j in ids[lo : min(hi, lo + top + 1)].tolist() if j != q]
                    if last is None and len(best) >= top:
                        last = score[k]  # nodes of this very score still count
                for s, j in sorted(best)[:top]:
                    out_q.append(q)
                    out_v.append(j)
                    out_s.append(-s)
        return pa.table({"query_id": pa.array(out_q, pa.int64()), "vec_id": pa.array(out_v, pa.int64()), "score": pa.array(out_s, pa.float64())})

    # One graph meets one block of queries in a group of bounded size.
    each = graphs.withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    found = each.groupBy("dim", "shard", "block").cogroup(sent.groupBy("dim", "shard", "block")).applyInArrow(find, "query_id long, vec_id long, score double")
    order = Window.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= top).select("query_id", "rank", "vec_id", "score")


def op7_hnsw_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = store.materialise(usable(store.table(spark, sf_dir, "embeddings"), "vec_id", "embedding"), "vectors")
    counts = shard_counts(rows)
    graphs = store.materialise(build(rows, counts), "graphs")
    return search(graphs, rows.where(F.col("vec_id") % QUERY_EVERY == 0), counts)
