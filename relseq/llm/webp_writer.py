"""The encoder that stores media: many small files at a time, at array speed.

Each image is either a palette of its colours with bundled indices, or samples less their guesses by a predictor
(one mode a tile, chosen by entropy), with green taken off red and blue where that pays. What is left is written
with back-references (the last place where three pixels stood in a row, as far as they agree), a colour cache
(where that pays) and prefix codes fitted to the image. Equal pixels give equal files, whatever stands beside them:
arrays run over all images of a batch, but nothing is shared between images.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np

from relseq.llm import webp

TILE_BITS = 6
MODES = (0, 1, 2, 4, 7, 12)
LEAST_COPY = 3
MOST_COPY = 4096
MOST_PLACES = 1 << 24  # pixels of a batch whose places fit beside 40 bits of a hash
FARTHEST = (1 << 20) - 120
MOST_CODE_BITS, MOST_META_BITS = 15, 7
SYMBOL_BITS = 5  # about what a symbol's code length takes in the header
META_ORDER = np.array(webp.LENGTH_ORDER)
BATCH_BYTES = 2 << 20  # samples encoded at a time
BLOCK_ROWS = 256  # rows whose samples are counted at a time, so that they stay in the processor's cache
LARGE, LEAST_LARGE = 48, 64  # so many of the largest trees are built alone, but none of so few symbols
GREEN_SYMBOLS, CACHE_SYMBOLS, FAR_SYMBOLS = 280, 1024, 40
#: Parts of an image in the stream: its head, three for each of five codes, its tokens.
PARTS = 17
_BIG = np.int64(1) << 60
#: n log2(n) for small n.
_N_LOG_N = np.arange(1 << 12) * np.log2(np.maximum(np.arange(1 << 12), 1))


def _starts(sizes: np.ndarray) -> np.ndarray:
    return np.cumsum(sizes) - sizes


def _counted(rows: np.ndarray, values: np.ndarray, n: int, width: int) -> np.ndarray:
    """How often each value below ``width`` stands in each of ``n`` rows."""
    return np.bincount(rows * width + values, minlength=n * width).reshape(n, width)


def n_log_n(counts: np.ndarray) -> np.ndarray:
    if counts.max(initial=0) < len(_N_LOG_N):
        return _N_LOG_N[counts]
    return counts * np.log2(np.maximum(counts, 1))


def entropies(counts: np.ndarray) -> np.ndarray:
    """For each row: bits that symbols with these counts take, and their codes' header."""
    used, total = np.count_nonzero(counts, axis=1), counts.sum(axis=1)
    return np.where(used < 2, 0.0, n_log_n(total) - n_log_n(counts).sum(axis=1) + SYMBOL_BITS * used)


def code_lengths(counts: np.ndarray, most: int, sizes: np.ndarray | None = None) -> np.ndarray:
    """Lengths of shortest prefix codes, none above ``most`` bits (rare symbols are taken for less rare until so).
    ``sizes``: the alphabets that ``counts`` holds one after the other."""
    sizes = np.array([len(counts)]) if sizes is None else sizes
    out = np.zeros(len(counts), np.int64)
    used = np.flatnonzero(counts)
    by = np.repeat(np.arange(len(sizes)), sizes)[used]
    many = np.bincount(by, minlength=len(sizes))
    out[used] = 1
    floor, todo = np.zeros(len(sizes), np.int64), many >= 2
    while todo.any():
        pick = todo[by]
        symbol, code = used[pick], by[pick]
        weight = np.maximum(counts[symbol], floor[code])
        order = np.argsort(code << 32 | weight, kind="stable")
        weight, each = weight[order], np.flatnonzero(todo)
        size, start = many[each], _starts(many[each])
        large = size > max(LEAST_LARGE, int(np.partition(size, -LARGE)[-LARGE]) if len(size) > LARGE else 0)
        depth, small = np.empty(len(weight), np.int64), np.repeat(~large, size)
        if small.any():
            depth[small] = _depths(weight[small], size[~large])
        for at, n in zip(start[large].tolist(), size[large].tolist()):
            depth[at : at + n] = _depths_alone(weight[at : at + n].tolist())
        out[symbol[order]] = depth
        floor[each] = 2 * floor[each] + 1 + (np.add.reduceat(weight, start) >> most)
        todo[each[depth[start] <= most]] = False  # the lightest symbol lies deepest
    return out


def _depths_alone(weights: list[int]) -> list[int]:
    """``_depths`` of one tree, a join at a time."""
    n, end = len(weights), float("inf")
    leaves, inner, parent = [*weights, end], [], [0] * (2 * n - 1)
    a = b = 0
    for fresh in range(n, 2 * n - 1):
        inner.append(end)  # the join's own place, not made yet
        total = 0
        for _ in range(2):
            if leaves[a] <= inner[b]:
                total += leaves[a]
                parent[a] = fresh
                a += 1
            else:
                total += inner[b]
                parent[n + b] = fresh
                b += 1
        inner[-1] = total
    depth = [0] * (2 * n - 1)
    for node in range(2 * n - 3, -1, -1):
        depth[node] = depth[parent[node]] + 1
    return depth[:n]


def _depths(weights: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Depths in Huffman trees of sorted weights, two or more each. Trees grow side by side, each by two queues
    (leaves, and inner nodes in the order they were made); larger trees come first, so those not done are a prefix."""
    rank = np.argsort(-sizes, kind="stable")
    m = sizes[rank]
    lane, within = np.repeat(np.arange(len(m)), m), np.arange(m.sum()) - np.repeat(_starts(m), m)
    source = _starts(sizes)[rank][lane] + within
    low, node = _starts(m + 1), 2 * _starts(m)
    leaves, inner = np.full(int((m + 1).sum()), _BIG + 1), np.full(int((m + 1).sum()), _BIG)
    leaves[low[lane] + within] = weights[source]
    parent = np.zeros(int(2 * m.sum()), np.int64)
    leaf, made = low.copy(), low.copy()
    to_leaf, to_inner = node - low, node + m - low
    joins = np.bincount(m - 1, minlength=int(m[0]))
    active = len(m) - np.cumsum(joins)  # trees with more joins than so many
    for step in range(int(m[0]) - 1):
        k = int(active[step])
        a, b, total, fresh = leaf[:k], made[:k], 0, node[:k] + m[:k] + step
        for _ in range(2):
            x, y = leaves[a], inner[b]
            first = x <= y
            total = total + np.minimum(x, y)
            parent[np.where(first, a + to_leaf[:k], b + to_inner[:k])] = fresh
            a += first
            b += ~first
        inner[low[:k] + step] = total
    depth, root = np.zeros(len(parent), np.int64), node + 2 * m - 2
    for step in range(1, 2 * int(m[0]) - 1):
        at = root[: int(active[(step - 1) >> 1])] - step
        depth[at] = depth[parent[at]] + 1
    out = np.empty(len(weights), np.int64)
    out[source] = depth[node[lane] + within]
    return out


def bit_codes(lengths: np.ndarray, owner: np.ndarray) -> np.ndarray:
    """Canonical codes, as they stand in the stream (first bit lowest); codes of one symbol have no lengths here."""
    used = np.flatnonzero(lengths)
    out = np.zeros(len(lengths), np.int64)
    used = np.sort((owner[used] << 4 | lengths[used]) << 32 | used) & 0xFFFFFFFF
    span = 1 << (MOST_CODE_BITS - lengths[used])
    # The spans of a code fill all of 15 bits, so the next one begins at 0 again.
    out[used] = webp.REVERSED_BITS[_starts(span) & ((1 << MOST_CODE_BITS) - 1)]
    return out


def write_codes(counts: np.ndarray, sizes: np.ndarray):
    """Codes for alphabets one after the other: codes and how many bits each takes, and the headers' fields as
    (code, part, value, bits)."""
    n = len(sizes)
    owner, start = np.repeat(np.arange(n), sizes), _starts(sizes)
    used = np.flatnonzero(counts)
    many = np.bincount(owner[used], minlength=n)
    ends = np.cumsum(many)
    padded = np.append(used, 0)
    lowest = np.where(many > 0, padded[np.minimum(ends - many, len(used))] - start, 0)
    highest = np.where(many > 0, padded[ends - 1] - start, 0)
    lengths = code_lengths(counts, MOST_CODE_BITS, sizes)
    bits = np.where(many[owner] > 1, lengths, 0)
    short = (many <= 2) & (highest < 256)
    two = many == 2
    each = np.flatnonzero(short)
    fields = [(each, 0, 5 | two[each] << 1 | lowest[each] << 3 | np.where(two, highest, 0)[each] << 11, 11 + 8 * two[each])]
    long = np.flatnonzero(~short)
    if len(long):
        pick = ~short[owner]
        number = np.cumsum(~short) - 1
        symbol, extra, extra_bits, code = _runs(lengths[pick], number[owner[pick]])
        k = len(long)
        meta = code_lengths(_counted(code, symbol, k, 19).ravel(), MOST_META_BITS, np.full(k, 19))
        meta_bits = np.where(np.repeat(np.count_nonzero(meta.reshape(k, 19), axis=1) > 1, 19), meta, 0)
        meta_codes = bit_codes(meta_bits, np.repeat(np.arange(k), 19))
        ordered = meta.reshape(k, 19)[:, META_ORDER]
        listed = np.maximum(4, 19 - np.argmax(ordered[:, ::-1] > 0, axis=1))
        fields.append((long, 0, (listed - 4) << 1, np.full(k, 5)))
        # After the lengths' own lengths, a bit that says they are given for the whole alphabet.
        ordered = np.append(ordered, np.zeros((k, 1), np.int64), axis=1)
        taken = np.append(np.where(np.arange(19) < listed[:, None], 3, 0), np.ones((k, 1), np.int64), axis=1)
        fields.append((np.repeat(long, 20), 1, ordered.ravel(), taken.ravel()))
        at = code * 19 + symbol
        fields.append((long[code], 2, meta_codes[at] | extra << meta_bits[at], meta_bits[at] + extra_bits))
    return bit_codes(bits, owner), bits, fields


def _runs(lengths: np.ndarray, owner: np.ndarray):
    """(symbol, extra, bits of extra, owner): code lengths with runs written as repeats."""
    change = np.ones(len(lengths), bool)
    change[1:] = (lengths[1:] != lengths[:-1]) | (owner[1:] != owner[:-1])
    starts = np.flatnonzero(change)
    size = np.append(starts[1:], len(lengths)) - starts
    value = lengths[starts]
    some = value > 0
    # A run is its value (unless 0), then the longest repeats, then a shorter one or single values.
    whole, rest = np.divmod(size - some, np.where(some, 6, 138))
    one = rest >= 3
    big = ~some & (rest > 10)
    count = np.stack((some, whole, np.where(one, 1, rest)), axis=1).ravel()
    zero = np.zeros(len(value), np.int64)
    symbol = np.stack((value, np.where(some, 16, 18), np.where(one, np.where(some, 16, np.where(big, 18, 17)), value)), axis=1).ravel()
    extra = np.stack((zero, np.where(some, 3, 127), np.where(one, rest - np.where(big, 11, 3), 0)), axis=1).ravel()
    bits = np.stack((zero, np.where(some, 2, 7), np.where(one, np.where(some, 2, np.where(big, 7, 3)), 0)), axis=1).ravel()
    # The four together in a number, so that they are repeated at once.
    all_of = np.repeat(symbol | extra << 5 | bits << 12 | np.repeat(owner[starts], 3) << 15, count)
    return all_of & 31, all_of >> 5 & 127, all_of >> 12 & 7, all_of >> 15


def numbers(values: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(symbol, extra, bits of extra) of lengths or distance codes."""
    v = values - 1
    top = np.frexp(np.maximum(v, 1))[1].astype(np.int64) - 1
    small = values <= 4
    up = np.maximum(top - 1, 0)
    half = v >> up & 1
    return np.where(small, v, 2 * top + half), np.where(small, 0, v & ((1 << up) - 1)), np.where(small, 0, up)


@lru_cache(512)
def near_codes(width: int) -> np.ndarray:
    """Short code of each near distance in an image of this width, 0 where there is none."""
    out = np.zeros(8 * width + 9, np.int64)
    for code in range(len(webp.NEAR), 0, -1):
        dx, dy = webp.NEAR[code - 1]
        if dx + dy * width >= 1:
            out[dx + dy * width] = code
    return out


def copies(flat: np.ndarray, image: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(place, length, distance) of the back-references to write, first come first served."""
    none = np.zeros(0, np.int64)
    n = len(flat) - (LEAST_COPY - 1)
    if n < 2:
        return none, none, none
    wide = flat.astype(np.uint64)
    key = (wide[:n] * np.uint64(0x9E3779B97F4A7C15) + wide[1 : n + 1]) * np.uint64(0xC2B2AE3D27D4EB4F) + wide[2 : n + 2]
    key = key * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(24)
    places = np.flatnonzero(image[:n] == image[2:])  # three pixels of one image
    if len(flat) <= MOST_PLACES:
        key = key[places] << np.uint64(24) | places.astype(np.uint64)
        key.sort()
        order, key = (key & np.uint64(MOST_PLACES - 1)).astype(np.int64), key >> np.uint64(24)
    else:
        order = np.argsort(key[places], kind="stable")
        order = places[order]
        key = key[order]
    # Images stand one after the other, so the last such place of the same image, if any, comes right before.
    again = np.flatnonzero(key[1:] == key[:-1])
    now, was = order[again + 1], order[again]
    own = image[now] == image[was]
    now, was = now[own], was[own]
    if not len(now):
        return none, none, none
    far = np.zeros(len(flat), np.int64)
    same = (flat[now] == flat[was]) & (flat[now + 1] == flat[was + 1]) & (flat[now + 2] == flat[was + 2]) & (now - was <= FARTHEST)
    far[now[same]] = (now - was)[same]
    # Where the distance stays the same the copy goes on; an image's last two places have none.
    starts = np.flatnonzero(np.diff(far, prepend=0))
    ends = np.append(starts[1:], len(far))
    held = far[starts] > 0
    out, at = [], 0
    for lo, hi, d in zip(starts[held].tolist(), ends[held].tolist(), far[starts[held]].tolist()):
        lo = max(lo, at)
        if lo < hi:
            at = hi + LEAST_COPY - 1
            while at - lo >= LEAST_COPY:
                size = min(at - lo, MOST_COPY)
                out.append((lo, size, d))
                lo += size
            at = lo
    return tuple(np.array(out, np.int64).reshape(-1, 3).T)


def write_images(images: list[tuple[int, np.ndarray]], heads: list[list[tuple[int, int]]], file_of: np.ndarray) -> list[bytes]:
    """The streams of files whose images are given in order as (width, ARGB pixels); each image has one group of codes.
    ``heads``: what stands before an image, as (value, bits); every file's second image is its main one."""
    n = len(images)
    # In an image of one colour every code has one symbol, and pixels take no bits.
    kept = [flat[:1] if (flat == flat[0]).all() else flat for _, flat in images]
    sizes = np.array([len(k) for k in kept])
    flat, image = np.concatenate(kept), np.repeat(np.arange(n), sizes)
    channels = np.ascontiguousarray(flat, "<u4").view(np.uint8).reshape(-1, 4)
    begin, size, distance = copies(flat, image)
    edge = np.zeros(len(flat) + 1, np.int64)
    edge[begin] += 1
    edge[begin + size] -= 1
    literal = np.flatnonzero(np.cumsum(edge[:-1]) == 0)
    size_symbol, size_extra, size_bits = numbers(size)
    copy_of, short = image[begin], np.zeros(len(begin), np.int64)
    wide = np.array([w for w, _ in images])[copy_of]
    for width in np.unique(wide).tolist():
        near, own = near_codes(width), wide == width
        d = distance[own]
        short[own] = near[np.minimum(d, len(near) - 1)] * (d < len(near))
    far_symbol, far_extra, far_bits = numbers(np.where(short > 0, short, distance + 120))

    # Literals and copies in order; a cached pixel is a literal with its place in the cache for a symbol.
    place = np.concatenate((literal, begin))
    order = np.argsort(place, kind="stable")
    rank = np.empty(len(place), np.int64)
    rank[order] = np.arange(len(place))
    token_of = image[place[order]]
    # Channels in memory order: blue, green, red, alpha; the codes' order begins with green and red.
    blue, green, red, alpha = (np.ascontiguousarray(c) for c in channels[literal].T)
    of = image[literal]
    lengths = _counted(copy_of, size_symbol + 256, n, GREEN_SYMBOLS)
    seen = [_counted(of, green, n, GREEN_SYMBOLS) + lengths, *(_counted(of, c, n, 256) for c in (red, blue, alpha))]
    plain, busy = np.zeros(n), np.flatnonzero(sizes > 1)
    plain[busy] = sum(entropies(c[busy]) for c in seen)
    cache_bits = np.clip(np.frexp(sizes)[1] - 3, 1, 10)
    slot = (flat * np.uint32(webp.CACHE_FACTOR)) >> (32 - cache_bits).astype(np.uint32)[image]
    key = image.astype(np.uint64) << np.uint64(43) | slot.astype(np.uint64) << np.uint64(32) | np.arange(len(flat), dtype=np.uint64)
    key.sort()
    by_slot = (key & np.uint64(0xFFFFFFFF)).astype(np.int64)
    key >>= np.uint64(32)
    known = np.zeros(len(flat), bool)
    known[by_slot[1:]] = (key[1:] == key[:-1]) & (flat[by_slot[1:]] == flat[by_slot[:-1]])
    hit, index = known[literal], slot[literal].astype(np.int64)
    tried = np.bincount(of[hit], minlength=n) > np.bincount(of, minlength=n) >> 6
    cached = np.zeros(n, bool)
    if tried.any():
        number, those = np.cumsum(tried) - 1, np.flatnonzero(hit & tried[of])
        row, m = number[of[those]], int(tried.sum())
        left = [all_of[tried] - _counted(row, c[those], m, all_of.shape[1]) for all_of, c in zip(seen, (green, red, blue, alpha))]
        left[0] = np.append(left[0], _counted(row, index[those], m, CACHE_SYMBOLS), axis=1)
        cached[tried] = sum(map(entropies, left)) < plain[tried]
    hit &= cached[of]

    alphabets = np.tile(np.array([GREEN_SYMBOLS, 256, 256, 256, FAR_SYMBOLS]), (n, 1))
    alphabets[:, 0] += np.where(cached, 1 << cache_bits, 0)
    base = _starts(alphabets.ravel()).reshape(n, 5)
    by_cache, uncached = np.flatnonzero(hit), np.flatnonzero(~hit)
    first = base[of, 0] + green
    first[by_cache] += GREEN_SYMBOLS + index[by_cache] - green[by_cache]
    left_of = of[uncached]
    others = [base[left_of, i] + c[uncached] for i, c in ((1, red), (2, blue), (3, alpha))]
    size_at, far_at = base[copy_of, 0] + 256 + size_symbol, base[copy_of, 4] + far_symbol
    counts = np.bincount(np.concatenate((first[by_cache], far_at)), minlength=int(alphabets.sum()))
    for i, (all_of, c) in enumerate(zip(seen, (green, red, blue, alpha))):
        if len(by_cache):
            all_of -= _counted(of[by_cache], c[by_cache], n, all_of.shape[1])
        counts[base[:, i, None] + np.arange(all_of.shape[1])] += all_of
    code, bits, fields = write_codes(counts, alphabets.ravel())

    # A token is green and red, then blue and alpha; or a copy's length, then its distance.
    value, taken = np.empty((2, len(place)), np.int64), np.empty((2, len(place)), np.int64)
    by_literal, by_copy = rank[: len(literal)], rank[len(literal) :]
    both = (code << 4 | bits).astype(np.int32)

    def coded(at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        found = both[at].astype(np.int64)
        return found >> 4, found & 15

    (half, size), (red, red_bits), (blue, blue_bits), (alpha, alpha_bits) = map(coded, (first, *others))
    if len(by_cache):
        half[uncached] |= red << size[uncached]
        size[uncached] += red_bits
    else:
        half |= red << size
        size += red_bits
    value[0, by_literal], taken[0, by_literal] = half, size
    own = by_literal[uncached]
    value[1], taken[1] = 0, 0
    value[1, own], taken[1, own] = blue | alpha << blue_bits, blue_bits + alpha_bits
    value[0, by_copy], taken[0, by_copy] = code[size_at] | size_extra << bits[size_at], bits[size_at] + size_bits
    value[1, by_copy], taken[1, by_copy] = code[far_at] | far_extra << bits[far_at], bits[far_at] + far_bits
    # Both halves are one field where that has no more than 33 bits.
    apart = taken[0] + taken[1] > 33
    field = np.arange(len(place)) + np.cumsum(apart) - apart
    values, widths = np.empty(len(place) + int(apart.sum()), np.int64), np.empty(len(place) + int(apart.sum()), np.int64)
    values[field], widths[field] = np.where(apart, value[0], value[0] | value[1] << taken[0]), np.where(apart, taken[0], taken[0] + taken[1])
    values[field[apart] + 1], widths[field[apart] + 1] = value[1, apart], taken[1, apart]

    main = np.append(file_of[1:] != file_of[:-1], True)
    for i, head in enumerate(heads):
        head.append((int(cached[i]) | int(cache_bits[i]) << 1, 5) if cached[i] else (0, 1))
        if main[i]:
            head.append((0, 1))
    head_fields = np.array([(i, value, size) for i, head in enumerate(heads) for value, size in head])
    groups = [(head_fields[:, 0] * PARTS, head_fields[:, 1], head_fields[:, 2])]
    groups += [(c // 5 * PARTS + 1 + 3 * (c % 5) + part, value, size) for c, part, value, size in fields]
    groups.append((np.repeat(token_of, 1 + apart) * PARTS + PARTS - 1, values, widths))
    return _join(groups, np.repeat(file_of, PARTS))


def _join(groups: list[tuple[np.ndarray, np.ndarray, np.ndarray]], file_of: np.ndarray) -> list[bytes]:
    """Fields as bytes. A group is (part, value, bits), ordered by part; ``file_of`` gives each part's file."""
    parts = len(file_of)
    each = [np.bincount(part, size, parts).astype(np.int64) for part, _, size in groups]
    bits = sum(each)
    total = np.bincount(file_of, bits).astype(np.int64)
    words = (total >> 5) + 2
    first = _starts(words)
    start = 32 * first[file_of] + _starts(bits) - _starts(total)[file_of]
    out = np.zeros(int(words.sum()))
    for (part, value, size), own in zip(groups, each):
        at = _starts(size) + (start - _starts(own))[part]
        shifted = value.astype(np.uint64) << (at & 31).astype(np.uint64)  # fields have at most 33 bits
        word = at >> 5
        # Fields never share a bit, so sums are unions; every sum stays below 2**32 and is exact.
        out += np.bincount(word, (shifted & np.uint64(0xFFFFFFFF)).astype(float), len(out))
        out += np.bincount(word + 1, (shifted >> np.uint64(32)).astype(float), len(out))
    data = out.astype(np.uint32).astype("<u4").tobytes()
    return [data[4 * a : 4 * a + (b + 7) // 8] for a, b in zip(first.tolist(), total.tolist())]


def _around(rows: np.ndarray, inner: np.ndarray):
    """Neighbours as ``webp.neighbours`` gives them, for the rows ``inner``."""
    above, own = rows[inner - 1].astype(np.int16), rows[inner].astype(np.int16)
    return own[:, :-1], above[:, 1:], np.concatenate((above[:, 2:], own[:, :1]), axis=1), above[:, :-1]


def choose_modes(rows: np.ndarray, inner: np.ndarray, tile: np.ndarray, tiles: int) -> np.ndarray:
    """The predictor's mode for each tile: the one whose residuals have the least entropy. ``inner``: rows that have
    one above them; ``tile``: the tile of each of their pixels but the first; channels without alpha, in any order."""
    if not tile.size:
        return np.zeros(tiles, np.int64)
    counts = np.zeros((len(MODES), tiles, 256), np.int64)
    for at in range(0, len(inner), BLOCK_ROWS):
        line, of = inner[at : at + BLOCK_ROWS], tile[at : at + BLOCK_ROWS]
        low, high = int(of.min()), int(of.max()) + 1
        around, own, base = _around(rows, line), rows[line, 1:], (of - low << 8)[..., None]
        for k, mode in enumerate(MODES):
            guess = webp.predictions(mode, *around).astype(np.uint8) if mode else np.uint8(0)
            counts[k, low:high] += np.bincount((base + (own - guess)).ravel(), minlength=high - low << 8).reshape(-1, 256)
    return np.array(MODES)[np.argmin([-n_log_n(c).sum(axis=1) for c in counts], axis=0)]


def residuals(rows: np.ndarray, top: np.ndarray, inner: np.ndarray, each: np.ndarray) -> np.ndarray:
    """Pixels less their guesses; ``top``: rows with none above, ``each``: modes of the inner rows' pixels."""
    out = rows.copy()
    out[top, 1:] = rows[top, 1:] - rows[top, :-1]
    out[top, 0] = rows[top, 0] - webp.BLACK.astype(np.uint8)
    out[inner, 0] = rows[inner, 0] - rows[inner - 1, 0]
    out[inner, 1:, 3] -= webp.BLACK.astype(np.uint8)[3]  # mode 0
    for mode in np.unique(each[each > 0]).tolist():
        here = (each == mode).any(axis=1)
        line = inner[here]
        guess = webp.predictions(mode, *_around(rows, line)).astype(np.uint8)
        out[line, 1:] = np.where((each[here] == mode)[..., None], rows[line, 1:] - guess, out[line, 1:])
    return out


def _of_channels(rows: np.ndarray, owner: np.ndarray, n: int, channels: tuple[int, ...] = (0, 1, 2)) -> list[np.ndarray]:
    """Bits of each owner's blue, green and red samples; owners ascend."""
    counts = np.zeros((len(channels), n, 256), np.int64)
    step = BLOCK_ROWS * max(1, 256 // max(1, rows[:1, ..., 0].size))
    for at in range(0, len(rows), step):
        of, some = owner[at : at + step], rows[at : at + step]
        low, high = int(of[0]), int(of[-1]) + 1
        base = (of - low << 8).reshape(-1, *[1] * (some.ndim - 2))
        for k, c in enumerate(channels):
            counts[k, low:high] += np.bincount((base + some[..., c]).ravel(), minlength=high - low << 8).reshape(-1, 256)
    return [entropies(c) for c in counts]


def encode(rgb: np.ndarray) -> bytes:
    """height x width x 3 samples -> a file."""
    return encode_many([rgb])[0]


def encode_many(pictures: list[np.ndarray]) -> list[bytes]:
    """A file for each picture of height x width x 3 samples."""
    out = [b""] * len(pictures)
    widths: dict[int, list[int]] = {}
    for i, picture in enumerate(pictures):
        widths.setdefault(picture.shape[1], []).append(i)
    for group in widths.values():
        held, size = [], 0
        for i in [*group, None]:
            if held and (i is None or size + pictures[i].size > BATCH_BYTES):
                for j, data in zip(held, _encode([pictures[j] for j in held])):
                    out[j] = data
                held, size = [], 0
            if i is not None:
                held.append(i)
                size += pictures[i].size
    return out


def _encode(pictures: list[np.ndarray]) -> list[bytes]:
    """Files of pictures of one width."""
    n, width = len(pictures), pictures[0].shape[1]
    heights = np.array([len(p) for p in pictures])
    first, owner = _starts(heights), np.repeat(np.arange(n), heights)
    rows = np.empty((len(owner), width, 4), np.uint8)
    rgb = np.concatenate(pictures)
    rows[..., :3], rows[..., 3] = rgb[..., ::-1], 255
    y = np.arange(len(owner)) - first[owner]
    across = webp._blocks(width, TILE_BITS)
    tiles = webp._blocks(heights, TILE_BITS) * across
    tile_at, inner = _starts(tiles), np.flatnonzero(y)
    tile = (tile_at[owner] + (y >> TILE_BITS) * across)[inner][:, None] + (np.arange(1, width) >> TILE_BITS)
    modes = choose_modes(rgb, inner, tile, int(tiles.sum()))
    rest = residuals(rows, first, inner, modes[tile])
    off = rest.copy()
    off[..., 0] -= rest[..., 1]
    off[..., 2] -= rest[..., 1]
    each = _of_channels(rest, owner, n)
    plain, (blue, red) = sum(each), _of_channels(off, owner, n, (0, 2))
    green = blue + each[1] + red < plain
    body = np.where(green[owner][:, None, None], off, rest).view("<u4")[..., 0].reshape(-1)

    argb = rows.view("<u4")[..., 0]
    colour = np.sort((owner.astype(np.uint64) << np.uint64(32))[:, None] | argb, axis=None)
    begin = np.flatnonzero(np.append(True, colour[1:] != colour[:-1]))
    pixels, colour = np.diff(np.append(begin, len(colour))), colour[begin]
    colour_of = (colour >> np.uint64(32)).astype(np.int64)
    colours = np.bincount(colour_of, minlength=n)
    few = (colours <= 256)[colour_of]
    table, pixels, colour_of = colour.astype("<u4")[few], pixels[few], colour_of[few]
    colour_at = _starts(np.where(colours <= 256, colours, 0))
    deltas = table.view(np.uint8).reshape(-1, 4).copy()
    within = np.flatnonzero(colour_of[1:] == colour_of[:-1]) + 1
    deltas[within] -= table.view(np.uint8).reshape(-1, 4)[within - 1]
    indices = n_log_n(heights * width) - np.bincount(colour_of, n_log_n(pixels), n) + SYMBOL_BITS * colours
    palette = (colours <= 256) & (sum(_of_channels(deltas, colour_of, n)) + np.where(colours < 2, 0.0, indices) < plain)
    shades = (modes << 8).astype(np.uint32) | np.uint32(0xFF000000)
    images, heads = [], []
    for i, (at, height) in enumerate(zip(first.tolist(), heights.tolist())):
        head = [(0x2F | (width - 1) << 8, 22), (height - 1, 18), (1, 1)]
        if palette[i]:
            mine = slice(colour_at[i], colour_at[i] + colours[i])
            fold = webp._bundle(int(colours[i]))
            wide = webp._blocks(width, fold)
            index = np.searchsorted(table[mine], argb[at : at + height])
            index = np.pad(index, ((0, 0), (0, (wide << fold) - width))).reshape(height, wide, 1 << fold)
            packed = (index << (np.arange(1 << fold) * (8 >> fold))).sum(axis=2).astype(np.uint32).ravel()
            images += [(int(colours[i]), deltas[mine].view("<u4").ravel()), (wide, packed << np.uint32(8) | np.uint32(0xFF000000))]
            heads += [[*head, (webp.PALETTE, 2), (int(colours[i]) - 1, 8)], [(0, 1)]]
            continue
        images.append((across, shades[tile_at[i] : tile_at[i] + tiles[i]]))
        images.append((width, body[at * width : (at + height) * width]))
        heads += [[*head, (webp.PREDICTOR, 2), (TILE_BITS - 2, 3)], [*([(1, 1), (webp.GREEN, 2)] if green[i] else []), (0, 1)]]
    return [webp._file(stream) for stream in write_images(images, heads, np.repeat(np.arange(n), 2))]
