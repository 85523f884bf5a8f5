"""Repeated byte strings by a distributed merge sort of front-coded suffix runs.

A byte is removed if a string of ``LENGTH`` bytes over it also starts in a document with a smaller id.

1. Anchors. Of the ``GRAM``-byte strings inside each window of ``LENGTH`` bytes the one with the smallest hash
   is the window's anchor, so equal windows have it at the same place, and about one position in 17 is one.
2. Candidates. Sorted runs of anchor hashes meet by hash bucket; an anchor that only one document has is
   dropped. A hash that several documents of a run share is sent once, so no bucket grows with its copies.
3. Runs. Each block of documents sorts the suffixes at its candidate anchors, followed by what stands before
   them read backwards, as far as a window can reach. Of equal entries the smallest document's stays and the
   others are removed there and then. Entries are front-coded: common prefix length and the rest.
4. Merge. A loser tree merges a bucket's runs; entries carry the prefix they share with the last winner,
   so known prefixes are never compared again. The prefixes that neighbours share in the merged order cut it into
   intervals: entries of one interval agree from the anchor on for that many bytes. What stands before the anchors
   is ordered likewise, and a window around an anchor repeats just where both its halves lie in one interval; the
   smallest document there keeps it. Bytes decide throughout, and hashes only say what meets where.
5. Removal. Marks meet their texts by block, and removed bytes are cut out.

Defined results: null text is empty; a null id sorts before all others; rows with equal id are one document
(neither removes from the other); texts shorter than a window lose nothing; ties in id do not occur
otherwise; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relseq.llm import store
from relseq.llm import text_kernels as tk

LENGTH = 50
GRAM = 16
REACH = LENGTH - GRAM
SPAN = LENGTH + REACH
U = np.uint64
CHUNK = 1 << 20
PLACE_BITS = 21
RUN_ANCHORS = 1_500_000
PART_BYTES = 4 << 20  # of stored input for each block of documents and each bucket of hashes
KNOWN = np.uint32(0xFFFFFFFF)
NULL_ID = -(2**63)
PACKED = "key int, a binary, b binary, c binary"
_ODD = (U(0x9E3779B97F4A7C15), U(0xC2B2AE3D27D4EB4F), U(0x165667B19E3779F9), U(0xD6E8FEB86659FD93), U(0xA0761D6478BD642F), U(0xE7037ED1A0B428DB), U(0x8EBC6AF09C88C6E3))


def _loads(data: np.ndarray, at: int, n: int) -> np.ndarray:
    """The 8 bytes from every position ``at .. at + n`` as integers, unaligned."""
    return np.ndarray((n,), U, data, at, (1,))


def gram_hashes(data: np.ndarray, n: int) -> np.ndarray:
    """Hashes of the GRAM bytes from each of the first ``n`` positions; ``data`` has GRAM spare bytes."""
    h = _loads(data, 0, n) * _ODD[0]
    h ^= h >> U(29)
    h += _loads(data, 8, n) * _ODD[1]
    h ^= h >> U(32)
    h *= U(0xBF58476D1CE4E5B9)
    h ^= h >> U(32)
    return h


def anchors(data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Positions of anchors of all windows that lie inside a text, and their hashes."""
    places, hashes = [np.zeros(0, np.int64)], [np.zeros(0, U)]
    wide = LENGTH - GRAM + 1
    for c in range(0, len(data), CHUNK):
        end = min(len(data), c + CHUNK + LENGTH - 1)
        n = end - c
        if n < LENGTH:
            continue
        part = np.concatenate((data[c:end], np.zeros(GRAM, np.uint8)))
        h = gram_hashes(part, n)
        m = (h & ~U((1 << PLACE_BITS) - 1)) | np.arange(n, dtype=U)
        size = 1
        while 2 * size <= wide:
            m = np.minimum(m[:-size], m[size:])
            size *= 2
        if size < wide:
            m = np.minimum(m[: len(m) - (wide - size)], m[wide - size :])
        m = m[: min(CHUNK, n - LENGTH + 1)]
        first, last = np.searchsorted(off, c, "right") - 1, np.searchsorted(off, c + len(m), "left")
        bounds = np.clip(off[first : last + 1] - c, 0, len(m))
        inside = np.arange(len(m)) + LENGTH <= np.repeat(off[first + 1 : last + 1] - c, np.diff(bounds))
        at = (m[inside] & U((1 << PLACE_BITS) - 1)).astype(np.int64)
        at = np.unique(at[np.concatenate(([True], at[1:] != at[:-1]))]) if len(at) else at
        places.append(at + c)
        hashes.append(h[at])
    at, h = np.concatenate(places), np.concatenate(hashes)
    if len(data) > CHUNK:
        at, own = np.unique(at, return_index=True)
        h = h[own]
    return at, h


def _row(key: int, *parts: np.ndarray) -> tuple:
    return (key, *(p.tobytes() for p in parts))


def _pack(rows: list[tuple]) -> pa.RecordBatch:
    cols = list(zip(*rows))
    return pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int32()), *(pa.array(c, pa.binary()) for c in cols[1:])], ["key", "a", "b", "c"])


def _send(rows: Iterator[tuple], limit: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    held, size = [], 0
    for row in rows:
        held.append(row)
        size += sum(len(x) for x in row[1:])
        if size > limit or len(held) >= 1000:
            yield _pack(held)
            held, size = [], 0
    if held:
        yield _pack(held)


def _split(keys: np.ndarray, *parts: np.ndarray) -> Iterator[tuple]:
    """Rows (key, part bytes ...) for each distinct key, order kept inside."""
    order = np.argsort(keys, kind="stable")
    keys = keys[order]
    cuts = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1]))) if len(keys) else []
    for lo, hi in zip(cuts, [*cuts[1:], len(keys)]):
        yield _row(int(keys[lo]), *(p[order[lo:hi]] for p in parts))


def _groups(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, list[tuple[bytes, bytes, bytes]]]]:
    """Rows of packed batches by key; equal keys stand together."""
    key, held = None, []
    for batch in batches:
        for k, *parts in zip(batch.column(0).to_pylist(), *(batch.column(i) for i in (1, 2, 3))):
            if key is not None and k != key:
                yield key, held
                held = []
            key = k
            held.append(tuple(p.as_buffer().to_pybytes() if p.is_valid else b"" for p in parts))
    if key is not None:
        yield key, held


def candidate_anchors(texts: DataFrame, blocks: int, buckets: int) -> DataFrame:
    """Packed (block; ids, places): anchors whose string is in several documents."""

    def runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        docs: list[np.ndarray] = []
        held: list[np.ndarray] = []
        places: list[np.ndarray] = []
        waiting = 0

        def flush() -> Iterator[tuple]:
            h, d, p = np.concatenate(held), np.concatenate(docs), np.concatenate(places)
            order = np.argsort(h, kind="stable")
            h, d, p = h[order], d[order], p[order]
            starts = np.flatnonzero(np.concatenate(([True], h[1:] != h[:-1])))
            several = np.minimum.reduceat(d, starts) != np.maximum.reduceat(d, starts)
            shared = np.repeat(several, np.diff(np.append(starts, len(h))))
            yield from ((-1 - k, a, b, b"") for k, a, b in _split(d[shared] % blocks, d[shared], p[shared]))
            lead = np.zeros(len(h), bool)
            lead[starts[several]] = True
            keep = ~shared | lead
            h, d, p = h[keep], d[keep], np.where(shared, KNOWN, p)[keep]
            yield from _split((h % U(buckets)).astype(np.int64), h, d, p)

        for batch in batches:
            data, off = tk.buffers(batch.column(1))
            ids = batch.column(0).to_numpy()
            for lo, hi, part, cuts in tk.slices(data, off):
                at, h = anchors(part, cuts)
                if len(at):
                    own = np.searchsorted(cuts, at, "right") - 1
                    docs.append(ids[lo + own])
                    held.append(h)
                    places.append((at - cuts[own]).astype(np.uint32))
                    waiting += len(at)
                if waiting >= RUN_ANCHORS:
                    yield from _send(flush())
                    docs, held, places, waiting = [], [], [], 0
        if waiting:
            yield from _send(flush())

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def rows():
            for key, found in _groups(batches):
                if key < 0:
                    yield from ((-1 - key, a, b, b"") for a, b, _ in found)
                    continue
                h, d, p = (np.frombuffer(b"".join(x), t) for x, t in zip(zip(*found), (U, np.int64, np.uint32)))
                order = np.argsort(h, kind="stable")
                h, d, p = h[order], d[order], p[order]
                starts = np.flatnonzero(np.concatenate(([True], h[1:] != h[:-1])))
                several = (np.minimum.reduceat(d, starts) != np.maximum.reduceat(d, starts)) | (np.maximum.reduceat(p, starts) == KNOWN)
                keep = np.repeat(several, np.diff(np.append(starts, len(h)))) & (p != KNOWN)
                yield from ((k, a, b, b"") for k, a, b in _split(d[keep] % blocks, d[keep], p[keep]))

        yield from _send(rows())

    return texts.select("id", "text").mapInArrow(runs, PACKED).repartition("key").sortWithinPartitions("key").mapInArrow(meet, PACKED)


def contexts(data: np.ndarray, at: np.ndarray, start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Entry bytes of anchors (suffix of LENGTH bytes, then REACH bytes before it backwards; zero beyond the text),
    and how far the text reaches to the left and to the right."""
    left = np.minimum(at - start, REACH).astype(np.uint8)
    right = np.minimum(end - at - GRAM, REACH).astype(np.uint8)
    step = np.concatenate((np.arange(LENGTH), -1 - np.arange(REACH)))
    padded = np.concatenate((np.zeros(REACH, np.uint8), data, np.zeros(LENGTH, np.uint8)))
    rows = padded[at[:, None] + (step + REACH)]
    rows[:, GRAM:LENGTH][np.arange(REACH) >= right[:, None]] = 0
    rows[:, LENGTH:][np.arange(REACH) >= left[:, None]] = 0
    return rows, left, right


def _order(rows: np.ndarray, *more: np.ndarray) -> np.ndarray:
    words = np.zeros((len(rows), (rows.shape[1] + 7) // 8 * 8), np.uint8)
    words[:, : rows.shape[1]] = rows
    words = words.view(">u8").astype(U)
    return np.lexsort((*reversed(more), *(words[:, i] for i in reversed(range(words.shape[1])))))


def _shared_prefix(rows: np.ndarray) -> np.ndarray:
    """Common prefix of each row with the one before it."""
    out = np.zeros(len(rows), np.uint8)
    if len(rows) > 1:
        differ = rows[1:] != rows[:-1]
        out[1:] = np.where(differ.any(axis=1), differ.argmax(axis=1), SPAN)
    return out


#: What an entry carries beside its bytes.
INFO = np.dtype([("id", "<i8"), ("tag", "<u4"), ("at", "<u4"), ("left", "u1"), ("right", "u1")])
MARK = np.dtype([("id", "<i8"), ("tag", "<u4"), ("lo", "<u4"), ("hi", "<u4")])


def _squeeze(data: bytes) -> bytes:
    return pa.compress(data, codec="zstd", asbytes=True)


def _open_run(shared: bytes, rest: bytes, info: bytes) -> tuple[bytes, bytes, np.ndarray]:
    """A run's prefix lengths, remaining bytes and information, as they were before the exchange."""
    n = len(shared)
    size = SPAN * n - int(np.frombuffer(shared, np.uint8).sum(dtype=np.int64))
    columns = pa.decompress(info, n * INFO.itemsize, codec="zstd", asbytes=True)
    out, at = np.zeros(n, INFO), 0
    for name in INFO.names:
        out[name] = np.frombuffer(columns, INFO[name], n, at)
        at += n * INFO[name].itemsize
    return shared, pa.decompress(rest, size, codec="zstd", asbytes=True), out


def front_code(rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Prefix lengths and the remaining bytes of sorted rows."""
    shared = _shared_prefix(rows)
    return shared, rows[np.arange(SPAN) >= shared[:, None]]


def _marks(info: np.ndarray, low: np.ndarray, high: np.ndarray) -> np.ndarray:
    """Windows that start ``high`` to ``low`` bytes before the anchor are removed."""
    out = np.zeros(len(info), MARK)
    out["id"], out["tag"] = info["id"], info["tag"]
    out["lo"], out["hi"] = info["at"] - high, info["at"] - low
    return out


def block_runs(rows: np.ndarray, info: np.ndarray, blocks: int, buckets: int) -> Iterator[tuple]:
    """Packed rows: sorted front-coded runs by bucket, and marks of what the block itself settles (key < 0)."""
    order = _order(rows, info["left"], info["right"], info["id"])
    rows, info = rows[order], info[order]
    same = np.zeros(len(rows), bool)
    same[1:] = (rows[1:] == rows[:-1]).all(axis=1) & (info["left"][1:] == info["left"][:-1]) & (info["right"][1:] == info["right"][:-1])
    lead = np.flatnonzero(~same)
    first = np.repeat(info["id"][lead], np.diff(np.append(lead, len(rows))))
    later = info["id"] > first
    own = info[later]
    marks = _marks(own, REACH - own["right"], own["left"])
    yield from ((-1 - k, m, b"", b"") for k, m in _split(marks["id"] % blocks, marks))
    rows, info = rows[~later], info[~later]
    bucket = (gram_hashes(np.ascontiguousarray(np.pad(rows, ((0, 0), (0, GRAM)))).ravel(), rows.size + GRAM * len(rows) - GRAM)[:: SPAN + GRAM] % U(buckets)).astype(np.int64)
    by = np.argsort(bucket, kind="stable")
    cuts = np.flatnonzero(np.concatenate(([True], bucket[by][1:] != bucket[by][:-1]))) if len(by) else []
    for lo, hi in zip(cuts, [*cuts[1:], len(by)]):
        mine = by[lo:hi]
        shared, rest = front_code(rows[mine])
        yield (int(bucket[mine[0]]), shared.tobytes(), _squeeze(rest.tobytes()), _squeeze(b"".join(np.ascontiguousarray(info[mine][f]).tobytes() for f in INFO.names)))


def merge_runs(runs: list[tuple[bytes, bytes]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Merge front-coded runs with a loser tree: (run of each entry, its place there, prefix shared with the
    entry before it in the merged order).

    Relative to the last winner, the entry that shares more of it is the smaller one; bytes are looked at only
    where two entries share equally much, and only behind that prefix.
    """
    count = len(runs)
    total = sum(len(s) for s, _ in runs)
    out_run, out_at, out_shared = np.zeros(total, np.int32), np.zeros(total, np.int32), np.zeros(total, np.uint8)
    if count == 1:
        return out_run, np.arange(total, dtype=np.int32), np.frombuffer(runs[0][0], np.uint8)
    size = 1 << (count - 1).bit_length()
    prefix = [s for s, _ in runs] + [b""] * (size - count)
    rest = [r for _, r in runs] + [b""] * (size - count)
    at, byte = [-1] * size, [0] * size
    key: list[bytes | None] = [b""] * size
    ends = [len(s) for s in prefix]

    def advance(r: int) -> int:
        """Next entry of run ``r``; returns the prefix it shares with the one before it there."""
        i = at[r] = at[r] + 1
        if i >= ends[r]:
            key[r] = None
            return -1
        h = prefix[r][i]
        b = byte[r]
        byte[r] = e = b + SPAN - h
        key[r] = key[r][:h] + rest[r][b:e]
        return h

    node: list[tuple[int, int]] = [(0, 0)] * size  # loser's run and the prefix it shares with the winner it met

    def play(a: int, ha: int, b: int, hb: int) -> tuple[int, int, int, int]:
        """(winner, its prefix, loser, its prefix); prefixes are with the last winner, the loser's then with this one."""
        x, y = key[a], key[b]
        if y is None:
            return a, ha, b, -1
        if x is None:
            return b, hb, a, -1
        if ha != hb:
            return (a, ha, b, hb) if ha > hb else (b, hb, a, ha)
        u, v = int.from_bytes(x[ha:], "big"), int.from_bytes(y[ha:], "big")
        if u == v:
            return (a, ha, b, SPAN) if a < b else (b, hb, a, SPAN)
        h = SPAN - (((u ^ v).bit_length() + 7) >> 3)
        return (a, ha, b, h) if u < v else (b, hb, a, h)

    level = []
    for r in range(size):
        advance(r)
        level.append((r, 0))
    base = size
    while base > 1:
        base //= 2
        up = []
        for i in range(base):
            (a, ha), (b, hb) = level[2 * i], level[2 * i + 1]
            w, hw, lo, hl = play(a, ha, b, hb)
            node[base + i] = (lo, hl)
            up.append((w, hw))
        level = up
    winner, shared = level[0]
    for n in range(total):
        out_run[n], out_at[n], out_shared[n] = winner, at[winner], shared
        r, h = winner, advance(winner)
        i = (size + r) >> 1
        while i:
            b, hb = node[i]
            if h < hb or (h == hb and h >= 0):
                r2, h2, lo, hl = play(r, h, b, hb)
                node[i] = (lo, hl)
                r, h = r2, h2
            i >>= 1
        winner, shared = r, h
    return out_run, out_at, out_shared


def unfold(shared: np.ndarray, rest: np.ndarray) -> np.ndarray:
    """Rows of a front-coded run."""
    n = len(shared)
    fresh = np.arange(SPAN) >= shared[:, None]
    rows = np.zeros((n, SPAN), np.uint8)
    rows[fresh] = rest
    source = np.maximum.accumulate(np.where(fresh, np.arange(n)[:, None], 0), axis=0)
    return rows[source, np.arange(SPAN)]


def settle(rows: np.ndarray, info: np.ndarray, shared: np.ndarray) -> np.ndarray:
    """Marks for a bucket's merged entries."""
    same = np.zeros(len(rows), bool)
    same[1:] = (shared[1:] == SPAN) & (info["left"][1:] == info["left"][:-1]) & (info["right"][1:] == info["right"][:-1])
    # Equal bytes with other reaches may stand between equal entries; they only make more classes.
    lead = np.flatnonzero(~same)
    counts = np.diff(np.append(lead, len(rows)))
    least = np.minimum.reduceat(info["id"], lead)
    of_class = np.repeat(np.arange(len(lead)), counts)
    later = info["id"] > least[of_class]
    own = info[later]
    out = [_marks(own, REACH - own["right"], own["left"])]

    # Classes of one anchor string are neighbours: compare their windows place by place.
    anchor = np.cumsum(np.concatenate(([True], shared[lead][1:] < GRAM)))
    many = np.bincount(anchor)[anchor] > 1
    cls = np.flatnonzero(many)
    if len(cls):
        left, right, ids = info["left"][lead[cls]], info["right"][lead[cls]], least[cls]
        # Intervals to the right: between two classes the least of the shared prefixes along the merged order.
        ahead = np.minimum.reduceat(np.append(shared[lead], 0), np.concatenate(([0], cls + 1)))[:-1]
        behind = rows[lead[cls]][:, LENGTH:]
        turn = _order(behind)
        sorted_behind = behind[turn]
        differ = sorted_behind[1:] != sorted_behind[:-1]
        back_shared = np.concatenate(([0], np.where(differ.any(axis=1), differ.argmax(axis=1), REACH))) if len(cls) > 1 else np.zeros(1, int)
        hit = np.zeros((REACH + 1, len(cls)), bool)
        for back in range(REACH + 1):  # windows that start ``back`` bytes before the anchor
            ok = np.flatnonzero((left >= back) & (right >= REACH - back))
            if len(ok) < 2:
                continue
            to_right = np.cumsum(ahead < LENGTH - back)
            to_left = np.empty(len(cls), np.int64)
            to_left[turn] = np.cumsum(back_shared < back)
            both = to_right[ok] * (len(cls) + 1) + to_left[ok]
            order = np.argsort(both, kind="stable")
            in_order = both[order]
            starts = np.flatnonzero(np.concatenate(([True], in_order[1:] != in_order[:-1])))
            if len(starts) == len(order):
                continue
            low = np.minimum.reduceat(ids[ok][order], starts)
            low = np.repeat(low, np.diff(np.append(starts, len(order))))
            hit[back, ok[order]] = low < ids[ok][order]
        # Runs of neighbouring places become one mark for each of the class's first document's entries.
        edge = np.diff(np.pad(hit, ((1, 1), (0, 0))).astype(np.int8), axis=0)
        first_back, c1 = np.nonzero(edge == 1)
        end_back, c2 = np.nonzero(edge == -1)
        o1, o2 = np.lexsort((first_back, c1)), np.lexsort((end_back, c2))
        low, high, c = first_back[o1], end_back[o2] - 1, c1[o1]
        if len(c):
            firsts = np.flatnonzero(~later)
            class_of = of_class[firsts]
            begin, stop = np.searchsorted(class_of, cls[c], "left"), np.searchsorted(class_of, cls[c], "right")
            n = stop - begin
            pick = np.repeat(begin, n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
            out.append(_marks(info[firsts[pick]], np.repeat(low, n), np.repeat(high, n)))
    return np.concatenate(out)


def removal_marks(texts: DataFrame, candidates: DataFrame, blocks: int, buckets: int) -> DataFrame:
    """Packed (block; marks): ranges of window starts to remove."""

    def sort_block(left: pa.Table, right: pa.Table) -> pa.Table:
        out: list[tuple] = []
        if left.num_rows and right.num_rows:
            ids = np.frombuffer(b"".join(x.as_py() for x in right.column("a")), np.int64)
            places = np.frombuffer(b"".join(x.as_py() for x in right.column("b")), np.uint32).astype(np.int64)
            order = np.lexsort((places, ids))
            ids, places = ids[order], places[order]
            found, infos = [], []
            for doc, cell in zip(left.column("id").to_pylist(), left.column("text")):
                raw = cell.as_buffer()
                data = np.frombuffer(raw, np.uint8)
                at = np.unique(places[np.searchsorted(ids, doc, "left") : np.searchsorted(ids, doc, "right")])
                at = at[at + GRAM <= len(data)]
                if len(at):
                    rows, before, behind = contexts(data, at, 0, len(data))
                    info = np.zeros(len(at), INFO)
                    info["id"], info["tag"], info["at"], info["left"], info["right"] = doc, zlib.crc32(raw), at, before, behind
                    fine = before.astype(int) + behind >= REACH
                    found.append(rows[fine])
                    infos.append(info[fine])
            if found:
                out = list(block_runs(np.concatenate(found), np.concatenate(infos), blocks, buckets))
        return pa.Table.from_batches([_pack([(k, *(x if isinstance(x, bytes) else x.tobytes() for x in p)) for k, *p in out])] if out else [], schema=pa.schema([("key", pa.int32()), ("a", pa.binary()), ("b", pa.binary()), ("c", pa.binary())]))

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def rows():
            for key, found in _groups(batches):
                if key < 0:
                    yield from ((-1 - key, a, b"", b"") for a, _, _ in found)
                    continue
                opened = [_open_run(*x) for x in found]
                run, at, shared = merge_runs([(a, b) for a, b, _ in opened])
                unfolded = [unfold(np.frombuffer(a, np.uint8), np.frombuffer(b, np.uint8)) for a, b, _ in opened]
                start = np.concatenate(([0], np.cumsum([len(x) for x in unfolded])))[run] + at
                info = np.concatenate([c for _, _, c in opened])[start]
                marks = settle(np.concatenate(unfolded)[start], info, shared)
                yield from ((k, m, b"", b"") for k, m in _split(marks["id"] % blocks, marks))

        yield from _send(rows())

    sorted_runs = texts.groupBy("block").cogroup(candidates.groupBy("key")).applyInArrow(sort_block, PACKED)
    return sorted_runs.repartition("key").sortWithinPartitions("key").mapInArrow(merge, PACKED)


def cut(data: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, int]:
    """Which bytes go, and in how many runs; windows start at lo .. hi (inclusive)."""
    edge = np.zeros(len(data) + 1, np.int64)
    np.add.at(edge, lo, 1)
    np.add.at(edge, np.minimum(hi + LENGTH, len(data)), -1)
    gone = np.cumsum(edge[:-1]) > 0
    return gone, int(gone[0]) + int((gone[1:] & ~gone[:-1]).sum()) if len(gone) else 0


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", digest_only: bool = False) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept_sha256) and, unless ``digest_only``, the remaining bytes ``kept``."""
    stored = int(docs.select(text_col)._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())
    parts = 2 * min(1 << 29, max(8, stored // PART_BYTES)) + 1
    base = docs.select(F.coalesce(F.col(id_col).cast("long"), F.lit(NULL_ID).cast("long")).alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    texts = base.withColumn("block", F.pmod("id", F.lit(parts)).cast("int"))
    candidates = store.materialise(candidate_anchors(texts, parts, parts), "anchors")
    marks = store.materialise(removal_marks(texts, candidates, parts, parts), "marks")

    def finish(left: pa.Table, right: pa.Table) -> pa.Table:
        if not left.num_rows:
            return pa.table({"doc_id": pa.array([], pa.int64()), "n_bytes": pa.array([], pa.int64()), "n_removed": pa.array([], pa.int64()), "n_spans": pa.array([], pa.int64()), "kept_sha256": pa.array([], pa.string()), **({} if digest_only else {"kept": pa.array([], pa.binary())})})
        mark = np.frombuffer(b"".join(x.as_py() for x in right.column("a")), MARK) if right.num_rows else np.zeros(0, MARK)
        mark = mark[np.argsort(mark["id"], kind="stable")]
        ids, sizes, removed, spans, digests, rest = [], [], [], [], [], []
        for doc, cell in zip(left.column("id").to_pylist(), left.column("text")):
            raw = cell.as_buffer()
            own = mark[np.searchsorted(mark["id"], doc, "left") : np.searchsorted(mark["id"], doc, "right")]
            if len(own):
                own = own[own["tag"] == zlib.crc32(raw)]
            kept, n, k = raw, 0, 0
            if len(own):
                data = np.frombuffer(raw, np.uint8)
                gone, k = cut(data, own["lo"].astype(np.int64), own["hi"].astype(np.int64))
                n, kept = int(gone.sum()), data[~gone].tobytes()
            ids.append(None if doc == NULL_ID else doc)
            sizes.append(raw.size)
            removed.append(n)
            spans.append(k)
            digests.append(hashlib.sha256(kept).hexdigest())
            if not digest_only:
                rest.append(bytes(kept))
        out = {"doc_id": pa.array(ids, pa.int64()), "n_bytes": pa.array(sizes, pa.int64()), "n_removed": pa.array(removed, pa.int64()), "n_spans": pa.array(spans, pa.int64()), "kept_sha256": pa.array(digests, pa.string())}
        return pa.table(out if digest_only else out | {"kept": pa.array(rest, pa.binary())})

    schema = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + ("" if digest_only else ", kept binary")
    return texts.groupBy("block").cogroup(marks.groupBy("key")).applyInArrow(finish, schema)


def op1_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(store.table(spark, sf_dir, "documents"), digest_only=True)
