"""Maximal refinements of condensed sequences, held as arrays of numbers from the first step to the last.

Occurrences are grown for a few thousand sequences at a time, with a table that says which frequent skeleton follows
from which by one event. They are grown twice. First each task tells, by skeleton and slot, the nodes that reach the
threshold's share among its own sequences: a node that is frequent in all is frequent in some task, so nothing is
missed. Then leaf concepts are lifted to the deepest of these nodes, which changes no frequent vector; sequences
that agree in all their lifted rows of a skeleton become one with their number, and only these travel. A skeleton's
vectors are searched in one task over bitmaps of rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import islice
from math import ceil

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relseq.functions import taxonomy
from relseq.operators import patterns
from relseq.operators.corpus import Corpus

PIECE_EVENTS = 20_000  # events whose occurrences are held at a time
HELD_CELLS = 8_000_000  # lifted leaf concepts that a task holds before they are sent
SENT_CELLS = 1_000_000  # of those, in one value
MERGED_ROWS = 500_000  # rows of a skeleton that are merged before more come
MARKED = 2_000_000  # sequences times nodes that are marked in a table
VECTOR_BLOCK = 5_000
VECTORS = "skeleton string, vector array<string>, support long"


class Steps:
    """The frequent skeletons by number, and which of them an event leads to: ``next[k][skeleton, break, type]``, -1 if none."""

    def __init__(self, skeletons: list[str], types: list[str]) -> None:
        by_length: dict[int, list[str]] = {}
        for s in sorted(skeletons):
            by_length.setdefault(len(patterns.parse(s)[0]), []).append(s)
        self.types = types
        self.levels = [by_length[k] for k in sorted(by_length)]
        self.first = np.array([self.levels[0].index(t) if self.levels and t in self.levels[0] else -1 for t in types], np.int32)
        self.next = []
        for own, longer in zip(self.levels, self.levels[1:]):
            place = {s: i for i, s in enumerate(longer)}
            table = [[[place.get(s + sign + t, -1) for t in types] for sign in (patterns.SAME, patterns.BREAK)] for s in own]
            self.next.append(np.array(table, np.int32))


class Words:
    """Names by number, in a task."""

    def __init__(self) -> None:
        self.number: dict[str, int] = {}

    def of(self, flat: pa.Array) -> np.ndarray:
        words = flat.dictionary_encode()
        to = [self.number.setdefault("None" if w is None else w, len(self.number)) for w in words.dictionary.to_pylist()]
        if words.indices.null_count:
            to.append(self.number.setdefault("None", len(self.number)))
        return np.array(to, np.int64)[words.indices.fill_null(len(to) - 1).to_numpy(zero_copy_only=False)] if len(flat) else np.zeros(0, np.int64)


class Ancestors:
    """The nodes at and above each word, by number."""

    def __init__(self) -> None:
        self.nodes: dict[str, int] = {}
        self.above: list[list[int]] = []
        self.at_depth = np.zeros((0, 0), np.int64)  # by depth and word, -1 below the word

    def follow(self, words: Words) -> np.ndarray:
        if len(self.above) < len(words.number):
            for w in islice(words.number, len(self.above), None):
                self.above.append([self.nodes.setdefault(c, len(self.nodes)) for c in taxonomy.climb(w)[::-1] if c])
            self.at_depth = np.full((max(map(len, self.above), default=0), len(self.above)), -1, np.int64)
            for w, chain in enumerate(self.above):
                self.at_depth[: len(chain), w] = chain
        return self.at_depth


def _starts(sizes: np.ndarray) -> np.ndarray:
    return np.concatenate([[0], np.cumsum(sizes)]).astype(np.int64)


class Piece:
    """Some sequences: their events one after the other."""

    def __init__(self, batch: pa.RecordBatch, words: Words, types: list[str], unit: str) -> None:
        events, related = batch.column("events"), batch.column("related")
        self.weights = batch.column("weight").to_numpy(zero_copy_only=False)
        lengths = pc.list_value_length(events).to_numpy(zero_copy_only=False).astype(np.int64)
        flat = pa.StructArray.from_arrays(events.flatten().flatten(), fields=list(events.type.value_type))
        self.start = _starts(lengths)
        self.sequence = np.repeat(np.arange(len(lengths)), lengths)
        self.place = np.arange(len(flat)) - self.start[self.sequence]  # from 0
        self.end = self.start[self.sequence + 1]
        self.type = pc.index_in(flat.field("type"), pa.array(types, pa.string())).fill_null(-1).to_numpy(zero_copy_only=False)
        self.txn = flat.field("txn").to_numpy(zero_copy_only=False)
        at = {"event": lambda: flat.field("pos"), "element": lambda: pc.add(pc.add(flat.field("pos"), flat.field("txn")), -1), "transaction": lambda: flat.field("txn"), "time": lambda: flat.field("attrs").field("day")}[unit]()
        self.known = at.is_valid().to_numpy(zero_copy_only=False)
        self.at = at.cast(pa.int64()).fill_null(0).to_numpy(zero_copy_only=False)
        concepts = flat.field("concepts")
        self.concept_sizes = pc.list_value_length(concepts).to_numpy(zero_copy_only=False).astype(np.int64)
        self.concept_start = _starts(self.concept_sizes)
        self.concepts = words.of(concepts.flatten())
        pairs = pc.list_value_length(related).to_numpy(zero_copy_only=False).astype(np.int64)
        self.pair_start = _starts(pairs)
        inner = related.flatten()
        self.relation_sizes = pc.list_value_length(inner).to_numpy(zero_copy_only=False).astype(np.int64)
        self.relation_start = _starts(self.relation_sizes)
        self.relations = words.of(inner.flatten())

    def near(self, a: np.ndarray, b: np.ndarray, most: int) -> np.ndarray:
        return self.known[a] & self.known[b] & (self.at[b] - self.at[a] <= most)

    def occurrences(self, steps: Steps, max_gap: int | None, max_span: int | None, by_place: bool) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        """For each length: skeletons by number, and the events of each occurrence. ``by_place``: gaps count events."""
        if not steps.levels:
            return
        state = np.where(self.type >= 0, steps.first[self.type], -1)
        events = np.flatnonzero(state >= 0)
        state, events = state[events], events[:, None]
        yield 1, state, events
        for k, table in enumerate(steps.next, 2):
            states, grown = [], []
            rows, distance = np.arange(len(state)), 0
            while len(rows) and not (by_place and max_gap is not None and distance >= max_gap):
                distance += 1
                last = events[rows, -1]
                inside = last + distance < self.end[last]
                rows, last = rows[inside], last[inside]
                to = last + distance
                now = np.where(self.type[to] >= 0, table[state[rows], (self.txn[to] > self.txn[last]).astype(np.int8), self.type[to]], -1)
                fits = now >= 0
                if max_gap is not None and not by_place:
                    fits &= self.near(last, to, max_gap)
                if max_span is not None:
                    fits &= self.near(events[rows, 0], to, max_span)
                states.append(now[fits])
                grown.append(np.concatenate([events[rows[fits]], to[fits, None]], axis=1))
            state = np.concatenate(states) if states else state[:0]
            events = np.concatenate(grown) if grown else np.zeros((0, k), np.int64)
            if not len(state):
                return
            yield k, state, events

    def leaf_rows(self, events: np.ndarray) -> np.ndarray:
        """Words of the slots of occurrences of one skeleton: of each event its concepts, then its relations to the earlier ones."""
        slots = []
        for i in range(events.shape[1]):
            own = events[:, i]
            slots += self._values(self.concepts, self.concept_start[own], self.concept_sizes[own])
            for j in range(i):
                b = self.place[own]
                pair = self.pair_start[self.sequence[own]] + b * (b - 1) // 2 + self.place[events[:, j]]
                if len(self.relation_sizes):
                    slots += self._values(self.relations, self.relation_start[pair], self.relation_sizes[pair])
        return np.stack(slots, axis=1) if slots else np.zeros((len(events), 0), np.int64)

    @staticmethod
    def _values(words: np.ndarray, start: np.ndarray, sizes: np.ndarray) -> list[np.ndarray]:
        wide = int(sizes[0])
        if (sizes != wide).any():
            raise ValueError("events of one type have as many concepts each, and pairs of types as many relations")
        return [words[start + n] for n in range(wide)]


def _by_skeleton(piece: Piece, steps: Steps, limits: tuple[int | None, int | None, str]) -> Iterator[tuple[str, np.ndarray, np.ndarray]]:
    """(skeleton, sequences, leaf rows as words)."""
    max_gap, max_span, unit = limits
    for k, state, events in piece.occurrences(steps, max_gap, max_span, unit == "event"):
        order = np.argsort(state, kind="stable")
        cuts = np.searchsorted(state[order], np.arange(len(steps.levels[k - 1]) + 1))
        for n, name in enumerate(steps.levels[k - 1]):
            own = events[order[cuts[n] : cuts[n + 1]]]
            if len(own):
                yield name, piece.sequence[own[:, 0]], piece.leaf_rows(own)


def _pieces(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
    ends = np.cumsum(pc.list_value_length(batch.column("events")).to_numpy(zero_copy_only=False))
    at = 0
    while at < batch.num_rows:
        before = ends[at - 1] if at else 0
        to = max(at + 1, int(np.searchsorted(ends, before + PIECE_EVENTS, "right")))
        yield pa.RecordBatch.from_arrays([pa.concat_arrays([c.slice(at, to - at)]) for c in batch.columns], schema=batch.schema)
        at = to


def folded(columns: list[np.ndarray], rows: int) -> tuple[np.ndarray, np.ndarray]:
    """(a row of each kind, kind of each row) of rows given by columns of numbers."""
    key, size = np.zeros(rows, np.int32), 1
    for c in columns:
        radix = int(c.max()) + 1 if rows else 1
        if radix == 1:
            continue
        if size * radix >= 1 << 62:
            key = np.unique(key, return_inverse=True)[1]
            size = rows
        key = key.astype(np.int32 if size * radix < 1 << 31 else np.int64, copy=False) * radix + c
        size *= radix
    if size <= 4 * rows + 64:  # few keys: by place
        first = np.full(size, -1, np.int64)
        first[key[::-1]] = np.arange(rows - 1, -1, -1)
        used = np.flatnonzero(first >= 0)
        number = np.zeros(size, np.int32)
        number[used] = np.arange(len(used))
        return first[used], number[key]
    _, first, kind = np.unique(key, return_index=True, return_inverse=True)
    return first, kind.astype(np.int32)


def distinct(a: np.ndarray, most_a: int, b: np.ndarray, most_b: int) -> tuple[np.ndarray, np.ndarray]:
    """The different pairs, in order; numbers are below ``most_a`` and ``most_b``."""
    key = a.astype(np.int32 if most_a * most_b < 1 << 31 else np.int64) * most_b + b
    if most_a * most_b <= 32 * len(key) + 4096:  # dense enough to be marked
        marked = np.zeros(most_a * most_b, bool)
        marked[key] = True
        key = np.flatnonzero(marked)
    else:
        key = np.unique(key)
    return np.divmod(key, max(1, most_b))


def renumbered(sequences: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The sequences that are there, and their places among these."""
    there = np.zeros(int(sequences.max()) + 1, bool)
    there[sequences] = True
    return np.flatnonzero(there), (np.cumsum(there, dtype=np.int32) - 1)[sequences]


def merged(sequences: np.ndarray, rows: np.ndarray, weights: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(rows a sequence, weights, rows): sequences whose sets of rows are equal as one, those with most rows first.
    ``weights`` are by sequence number."""
    first, kind = folded(list(rows.T), len(rows))
    present, own = renumbered(sequences)
    own, kind = distinct(own, len(present), kind, len(first))
    sequences = present[own]
    begin = np.flatnonzero(np.concatenate([[True], sequences[1:] != sequences[:-1]]))
    number = np.diff(np.append(begin, len(sequences)))
    sizes, totals, out = [], [], []
    for m in np.unique(number)[::-1].tolist():
        own = begin[number == m]
        sets = kind[own[:, None] + np.arange(m)]
        one, same = folded(list(sets.T), len(sets))
        total = np.zeros(len(one), np.int64)
        np.add.at(total, same, weights[sequences[own]])
        order = np.argsort(-total, kind="stable")
        sizes.append(np.full(len(one), m, np.int32))
        totals.append(total[order])
        out.append(sets[one[order]].ravel())
    return np.concatenate(sizes), np.concatenate(totals), rows[first[np.concatenate(out)]]


def _ready(corpus: Corpus) -> DataFrame:
    return corpus.sequences.select("events", "related", F.col("weight").cast("long").alias("weight"))


def supports(sequences: np.ndarray, words: np.ndarray, at_depth: np.ndarray, weights: np.ndarray, nodes: int) -> np.ndarray:
    """By node: the sequences that have a word at or below it."""
    if len(weights) * nodes <= MARKED and int(weights.sum()) < 1 << 24:  # sums are exact in single precision
        marked = np.zeros((len(weights), nodes + 1), np.float32)  # the last column is for none
        flat, begin = marked.ravel(), sequences * (nodes + 1)
        for level in at_depth:
            at = level[words]
            flat[begin + np.where(at < 0, nodes, at)] = 1
        return (weights.astype(np.float32) @ marked)[:nodes].astype(np.int64)
    out = np.zeros(nodes, np.int64)
    sequences, words = distinct(sequences, len(weights), words, at_depth.shape[1])
    for level in at_depth:
        node = level[words]
        kept = node >= 0
        sequences, words = sequences[kept], words[kept]
        seen, one = distinct(sequences, len(weights), node[kept], nodes)
        np.add.at(out, one, weights[seen])
    return out


def frequent_nodes(corpus: Corpus, skeletons: list[str], theta: int, total: int, limits: tuple[int | None, int | None, str]) -> dict[str, list[list[str]]]:
    """By skeleton and slot: the nodes that can be in a frequent vector, sorted. Each task tells those that reach the
    threshold's share among its own sequences: bounded by the slots and the threshold, not by the data."""
    types = corpus.types
    steps = Steps(skeletons, types)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, number = Words(), 0
        ancestors = Ancestors()
        nodes = ancestors.nodes
        counts: dict[tuple[str, int], np.ndarray] = {}
        for batch in batches:
            number += int(batch.column("weight").to_numpy().sum())
            for part in _pieces(batch):
                piece = Piece(part, words, types, limits[2])
                at_depth = ancestors.follow(words)
                for name, sequences, rows in _by_skeleton(piece, steps, limits):
                    present, sequences = renumbered(sequences)
                    weights = piece.weights[present]
                    for s in range(rows.shape[1]):
                        own = counts.get((name, s))
                        if own is None or len(own) < len(nodes):
                            own = np.concatenate([own if own is not None else np.zeros(0, np.int64), np.zeros(len(nodes) - (0 if own is None else len(own)), np.int64)])
                            counts[name, s] = own
                        own += supports(sequences, rows[:, s], at_depth, weights, len(nodes))
        least = max(1, ceil(theta * number / max(1, total) - 1e-9))
        names = list(nodes)
        told = [(name, s, names[i]) for (name, s), own in counts.items() for i in np.flatnonzero(own >= least).tolist()]
        yield pa.RecordBatch.from_arrays([pa.array([t[0] for t in told], pa.string()), pa.array([t[1] for t in told], pa.int32()), pa.array([t[2] for t in told], pa.string())], ["skeleton", "slot", "node"])

    found = _ready(corpus).mapInArrow(run, "skeleton string, slot int, node string").distinct().collect()  # bounded as above
    out: dict[str, list[list[str]]] = {}
    for r in found:
        slots = out.setdefault(r["skeleton"], [])
        slots.extend([] for _ in range(r["slot"] + 1 - len(slots)))
        slots[r["slot"]].append(r["node"])
    return {name: [sorted(own) for own in slots] for name, slots in out.items()}


def _dtype(slots: list[list[str]]) -> np.dtype:
    return np.dtype(np.uint8 if max(map(len, slots), default=0) < 256 else np.uint32)


def lifted(corpus: Corpus, skeletons: list[str], nodes: dict[str, list[list[str]]], limits: tuple[int | None, int | None, str]) -> DataFrame:
    """(skeleton, sizes, weights, rows): merged sequences with their rows of one skeleton, slots as numbers of ``nodes``
    from 1, 0 for the root. The last slots of a skeleton that have no node are left out."""
    types = corpus.types
    steps = Steps(skeletons, types)
    schema = "skeleton string, sizes binary, weights binary, rows binary"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, ancestors = Words(), Ancestors()
        lift: dict[tuple[str, int], np.ndarray] = {}
        held: dict[str, list[tuple[np.ndarray, np.ndarray, np.ndarray]]] = {}
        cells: dict[str, int] = {}

        def send(name: str) -> Iterator[pa.RecordBatch]:
            sizes, weights, rows = joined(held.pop(name))
            del cells[name]
            ends = np.cumsum(sizes)
            step, at = max(1, SENT_CELLS // (rows.shape[1] + 4)), 0
            while at < len(sizes):
                before = int(ends[at - 1]) if at else 0
                to = max(at + 1, int(np.searchsorted(ends, before + step, "right")))
                part = [sizes[at:to], weights[at:to], rows[before : int(ends[to - 1])]]
                yield pa.RecordBatch.from_arrays([pa.array([name]), *[pa.array([np.ascontiguousarray(x).tobytes()], pa.binary()) for x in part]], ["skeleton", "sizes", "weights", "rows"])
                at = to

        for batch in batches:
            for part in _pieces(batch):
                piece = Piece(part, words, types, limits[2])
                at_depth = ancestors.follow(words)
                for name, sequences, rows in _by_skeleton(piece, steps, limits):
                    slots = nodes.get(name, [])
                    made = np.zeros((len(rows), len(slots)), _dtype(slots))
                    for s in range(len(slots)):
                        to = lift.get((name, s))
                        if to is None or len(to) < at_depth.shape[1]:
                            place = np.zeros(len(ancestors.nodes) + 1, np.int64)  # the last is for none
                            for i, c in enumerate(slots[s], 1):
                                place[ancestors.nodes.get(c, -1)] = i
                            place[-1] = 0
                            to = np.zeros(at_depth.shape[1], np.int64)
                            for level in at_depth:
                                to = np.where(place[level] > 0, place[level], to)
                            lift[name, s] = to
                        made[:, s] = to[rows[:, s]]
                    held.setdefault(name, []).append(merged(sequences, made, piece.weights))
                    cells[name] = cells.get(name, 0) + len(held[name][-1][2]) * (made.shape[1] + 4)
            while sum(cells.values()) > HELD_CELLS:
                largest = max(cells, key=cells.get)
                yield from send(largest)
        for name in list(held):
            yield from send(name)

    return _ready(corpus).mapInArrow(run, schema)


def joined(parts: list[tuple[np.ndarray, np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    sizes, weights, rows = (np.concatenate(x) for x in zip(*parts))
    return merged(np.repeat(np.arange(len(sizes), dtype=np.int32), sizes), rows, weights)


class Bitmaps:
    """Merged sequences as bits: a layer has the n-th row of all sequences that have so many, in the order of the
    sequences, so that layers laid over each other tell the sequences that have a row."""

    def __init__(self, sizes: np.ndarray, weights: np.ndarray, rows: np.ndarray, nodes: list[list[str]]) -> None:
        begin = _starts(sizes)[:-1]
        self.layers: list[tuple[int, int]] = []
        places = np.empty(len(rows), np.int64)
        at = 0
        for n in range(int(sizes[0])):
            own = begin[: int(np.searchsorted(-sizes, -n, "left"))] + n  # sizes fall
            places[own] = np.arange(len(own)) + 64 * at
            end = at + (len(own) + 63) // 64
            self.layers.append((at, end))
            at = end
        self.words = at
        self.all = self.bits(places)
        self.items: list[dict[str, np.ndarray]] = []
        self.children: list[dict[str, list[str]]] = []
        for s, own in enumerate(nodes):
            below = {c: np.zeros(len(own) + 1, bool) for c in own}
            kids: dict[str, list[str]] = {}
            for i, c in enumerate(own, 1):
                for up in taxonomy.climb(c):
                    if up in below:
                        below[up][i] = True
                kids.setdefault(c.rpartition("/")[0], []).append(c)
            self.items.append({c: self.bits(places[flags[rows[:, s]]]) for c, flags in below.items()})
            self.children.append(kids)
        wide = self.layers[0][1]
        self.planes = [self.bits(np.flatnonzero(weights >> b & 1), wide) for b in range(int(weights.max()).bit_length())] if (weights != 1).any() else []

    def bits(self, places: np.ndarray, words: int | None = None) -> np.ndarray:
        flags = np.zeros((self.words if words is None else words) * 64, bool)
        flags[places] = True
        return np.packbits(flags, bitorder="little").view(np.uint64)

    def support(self, bits: np.ndarray) -> int:
        a, b = self.layers[0]
        seen = bits[a:b]
        if len(self.layers) > 1:
            seen = seen.copy()
            for a, b in self.layers[1:]:
                np.bitwise_or(seen[: b - a], bits[a:b], out=seen[: b - a])
        if not self.planes:
            return int(np.bitwise_count(seen).sum(dtype=np.int64))
        return sum(int(np.bitwise_count(seen & p).sum(dtype=np.int64)) << n for n, p in enumerate(self.planes))


def frequent(maps: Bitmaps, theta: int, out: dict[bytes, int], ids: list[dict[str, bytes]]) -> None:
    """Every frequent vector: nodes are added from the left, each by descending its tree. What is not frequent
    beside fewer nodes is not looked at beside more."""
    root = [own[taxonomy.ROOT] for own in ids]

    def enter(chosen: bytes, s: int, c: str, bits: np.ndarray, n: int, later: list[tuple[int, str]]) -> None:
        """``chosen`` reaches up to slot ``s``, and ``later`` are first nodes of the slots after it."""
        here = chosen + ids[s][c]
        out[here + b"".join(root[s + 1 :])] = n
        alive = walk(here, s + 1, bits, later)
        for d in maps.children[s].get(c, ()):
            own = bits & maps.items[s][d]
            n = maps.support(own)
            if n >= theta:
                enter(chosen, s, d, own, n, alive)

    def walk(chosen: bytes, filled: int, bits: np.ndarray, candidates: list[tuple[int, str]]) -> list[tuple[int, str]]:
        alive = []
        for s, c in candidates:
            n = maps.support(bits & maps.items[s][c])
            if n >= theta:
                alive.append((s, c, n))
        for s, c, n in alive:
            enter(chosen + b"".join(root[filled:s]), s, c, bits & maps.items[s][c], n, [(t, d) for t, d, _ in alive if t > s])
        return [(s, c) for s, c, _ in alive]

    n = maps.support(maps.all)
    if n >= theta:
        out[b"".join(root)] = n
        walk(b"", 0, maps.all, [(s, c) for s, kids in enumerate(maps.children) for c in kids.get(taxonomy.ROOT, ())])


def maximal(maps: Bitmaps, theta: int, nodes: list[list[str]]) -> Iterator[tuple[list[str], int]]:
    """Frequent vectors of which none is one step narrower: each marks those one step broader, which are frequent too."""
    size = 1 if _dtype(nodes).itemsize == 1 else 4
    names = [[taxonomy.ROOT, *own] for own in nodes]
    ids = [{c: i.to_bytes(size, "little") for i, c in enumerate(own)} for own in names]
    found: dict[bytes, int] = {}
    frequent(maps, theta, found, ids)
    parent = [{ids[s][c]: ids[s][c.rpartition("/")[0]] for c in own} for s, own in enumerate(nodes)]
    slots = [(parent[s], s * size, (s + 1) * size) for s in range(len(nodes)) if nodes[s]]
    covered = set()
    for v in found:
        for up, a, b in slots:
            above = up.get(v[a:b])
            if above is not None:
                covered.add(v[:a] + above + v[b:])
    for v, n in found.items():
        if v not in covered:
            yield [names[s][int.from_bytes(v[s * size : (s + 1) * size], "little")] for s in range(len(nodes))], n


def refined(corpus: Corpus, skeletons: dict[str, tuple[int, int]], theta: int, total: int, limits: tuple[int | None, int | None, str], wide: dict[str, int]) -> DataFrame:
    """(skeleton, vector, support): the maximal vectors of each skeleton over a condensed corpus. ``wide``: slots of a
    skeleton."""
    names = sorted(skeletons)
    nodes = frequent_nodes(corpus, names, theta, total, limits)
    parts = lifted(corpus, names, nodes, limits)

    def report(name: str, parts: list[tuple[np.ndarray, np.ndarray, np.ndarray]]) -> Iterator[pa.RecordBatch]:
        slots = nodes.get(name, [])
        rest = [taxonomy.ROOT] * (wide[name] - len(slots))
        maps = Bitmaps(*joined(parts), slots)
        parts.clear()
        found = maximal(maps, theta, slots)
        while own := list(islice(found, VECTOR_BLOCK)):
            yield pa.RecordBatch.from_arrays([pa.array([name] * len(own), pa.string()), pa.array([v + rest for v, _ in own], pa.list_(pa.string())), pa.array([n for _, n in own], pa.int64())], ["skeleton", "vector", "support"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come by skeleton."""
        name, held, most = None, [], MERGED_ROWS
        for batch in batches:
            for i in range(batch.num_rows):
                own = batch.column(0)[i].as_py()
                if held and own != name:
                    yield from report(name, held)
                    held, most = [], MERGED_ROWS
                name = own
                sizes, weights, rows = (batch.column(c)[i].as_buffer() for c in (1, 2, 3))
                sizes = np.frombuffer(sizes, np.int32).copy()
                rows = np.frombuffer(rows, _dtype(nodes.get(name, []))).reshape(int(sizes.sum()), len(nodes.get(name, []))).copy()
                held.append((sizes, np.frombuffer(weights, np.int64).copy(), rows))
                if sum(len(p[2]) for p in held) > most:
                    held = [joined(held)]
                    most = max(MERGED_ROWS, 2 * len(held[0][2]))
        if held:
            yield from report(name, held)

    # The skeletons that may take long begin first, each in a task of its own where there are not too many.
    order = sorted(names, key=lambda s: -skeletons[s][1] * max(1, wide[s]))
    number = min(len(names), 400)
    to = {s: i % number for i, s in enumerate(order)}
    spark = corpus.sequences.sparkSession
    if not names:
        return spark.createDataFrame([], VECTORS)
    place = F.create_map(*[F.lit(x) for s, i in to.items() for x in (s, i)])
    dealt = parts.withColumn("to", F.element_at(place, F.col("skeleton"))).repartitionById(number, F.col("to")).drop("to")
    return dealt.sortWithinPartitions("skeleton").mapInArrow(run, VECTORS)
