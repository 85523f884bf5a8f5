"""Reads many lossless images at a time.

Prefix codes are read side by side, one code length of each image in a step. Tokens of main images are found from many
places at once: a stream is entered every ``SEGMENT`` bits, right or wrong, and each entry reads on until it stands
where another one has been (after a wrong entry the ends of tokens soon coincide with the right ones). The chain of
tokens from the first bit is then known, and its tokens are read as arrays. The small images of transforms are read a
token of each in a step. Copies and cached pixels become pointers to earlier pixels, followed for all images together.
Where few short images come together, and where an image has several groups of codes or entries that do not meet, images are
read one by one by ``webp.read_image``.
"""

from __future__ import annotations

import numpy as np

from relseq.llm import webp

ALONE = 4  # so few images of few pixels, and so many of a batch's longest images of transforms, are read one by one
FEW_PIXELS = 1 << 16
SEGMENT = 2048  # bits from one entry into a stream to the next
STRIDE = 16  # tokens that entries read before it is seen which have met others
MOST_ROUNDS = 16  # times that ways out of segments are carried on; images that need more are read one by one
MOST_STEPS = 4096  # tokens after which images whose entries have not met are read one by one
BATCH_PIXELS = 1 << 21  # pixels decoded at a time, unless one image has more
MOST_ENTRIES = 1 << 22  # entries of a code's tables held at a time; beyond them the images are read in halves
# Code lengths' symbols: how many lengths one stands for, and its extra bits.
_RUN_BASE = np.array([1] * 16 + [3, 3, 11])
_RUN_BITS = np.array([0] * 16 + [2, 3, 7])
_RUN_MASK = (1 << _RUN_BITS) - 1


class TooLarge(Exception):
    """The tables of these images together take too much memory."""


def decode_many(files: list[bytes]) -> list[np.ndarray]:
    """``webp.decode`` of every file."""
    out: list[np.ndarray] = []
    held, size = [], 0
    for data in map(webp.content, files):
        sides = int.from_bytes(data[1:5], "little")
        pixels = ((sides & 0x3FFF) + 1) * ((sides >> 14 & 0x3FFF) + 1)
        if held and size + pixels > BATCH_PIXELS:
            out += _decode(held)
            held, size = [], 0
        held.append(data)
        size += pixels
    return out + _decode(held)


def _decode(streams: list[bytes]) -> list[np.ndarray]:
    runs = [webp.steps(s) for s in streams]
    out: list[np.ndarray] = [None] * len(runs)
    asked = {i: next(run) for i, run in enumerate(runs)}
    while asked:
        found, further = read_images(list(asked.values())), {}
        for i, pixels in zip(asked, found):
            try:
                further[i] = runs[i].send(pixels)
            except StopIteration as done:
                out[i] = webp.samples(done.value)
        asked = further
    return out


def read_images(asked: list[tuple[webp.Bits, int, int, bool]]) -> list[np.ndarray]:
    """Flat pixels of each image asked for as (bits, width, height, main)."""
    totals = np.array([w * h for _, w, h, _ in asked])
    alone = np.array([main and _grouped(bits) for bits, _, _, main in asked], bool)
    if len(asked) <= ALONE and totals.sum() < FEW_PIXELS:
        alone[:] = True
    mains = np.array([main for _, _, _, main in asked], bool)
    parts = np.flatnonzero(~mains)
    if ALONE and len(parts) > ALONE:
        alone[parts] |= totals[parts] > np.sort(totals[parts])[-ALONE]
    out: list[np.ndarray] = [None] * len(asked)
    for i in np.flatnonzero(alone).tolist():
        out[i] = webp.read_image(*asked[i])
    for kind in (mains, ~mains):
        rest = np.flatnonzero(kind & ~alone).tolist()
        for i, pixels in zip(rest, _together([asked[i] for i in rest])):
            out[i] = pixels
    return out


def _grouped(bits: webp.Bits) -> bool:
    """Whether a main image has groups of codes; the flag follows the colour cache's."""
    window = bits.peek(6)
    return bool(window >> (5 if window & 1 else 1) & 1)


def _together(asked: list[tuple[webp.Bits, int, int, bool]]) -> list[np.ndarray]:
    if not asked:
        return []
    try:
        return _read(asked)
    except TooLarge:
        half = len(asked) // 2
        return _together(asked[:half]) + _together(asked[half:]) if half else [webp.read_image(*asked[0])]


def tables(lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Canonical codes by their lengths, one a row -> (entries, where a code's entries begin, its longest length). There
    is an entry for every value of the next ``longest`` bits: symbol << 4 | bits. One used symbol takes no bits."""
    n = len(lengths)
    many = np.count_nonzero(lengths, axis=1)
    lengths[many == 0, 0] = 1
    longest = np.where(many < 2, 0, lengths.max(axis=1))
    entries = 1 << longest
    if entries.sum() > MOST_ENTRIES:
        raise TooLarge
    lane, symbol = np.nonzero(lengths)
    size = np.where(many[lane] < 2, 0, lengths[lane, symbol])
    order = np.argsort(lane << 4 | size, kind="stable")
    lane, symbol, size = lane[order], symbol[order], size[order]
    span = 1 << (longest[lane] - size)
    if (np.bincount(lane, span, n).astype(np.int64) != entries).any():
        raise ValueError("a prefix code is not complete")
    begin = np.cumsum(entries) - entries
    first = np.repeat(begin, entries)
    within = np.arange(len(first)) - first
    return np.repeat((symbol << 4 | size).astype(np.int32), span)[first + (webp.REVERSED_BITS[within] >> (15 - np.repeat(longest, entries)))], begin, longest


def read_lengths(loads: np.ndarray, pos: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The lengths of one code from each place ``pos`` for alphabets of ``sizes``, and the places after them."""
    lengths = np.zeros((len(pos), max(256, int(sizes.max()))), np.int64)
    window = loads[pos >> 3] >> (pos & 7)
    short = (window & 1) == 1
    two, wide = short & ((window >> 1 & 1) == 1), (window >> 2 & 1) == 1
    taken = np.where(wide, 11, 4)
    each, both = np.flatnonzero(short), np.flatnonzero(two)
    lengths[each, (window >> 3 & np.where(wide, 255, 1))[each]] = 1
    lengths[both, (window >> taken & 255)[both]] = 1
    after = pos + taken + 8 * two

    lane = np.flatnonzero(~short)
    if not len(lane):
        return lengths, after
    size, listed, p = sizes[lane], 4 + (window[lane] >> 1 & 15), pos[lane] + 5
    window = loads[p >> 3] >> (p & 7)
    meta = np.zeros((len(lane), 19), np.int64)
    for i, symbol in enumerate(webp.LENGTH_ORDER):
        meta[:, symbol] = np.where(i < listed, window >> (3 * i) & 7, 0)
    p += 3 * listed
    window = loads[p >> 3] >> (p & 7)
    limited, extra = (window & 1) == 1, 2 + 2 * (window >> 1 & 7)
    most = np.where(limited, 2 + (window >> 4 & (1 << extra) - 1), size)
    p += np.where(limited, 4 + extra, 1)
    entries, begin, longest = tables(meta)
    mask, at, last = (1 << longest) - 1, np.zeros(len(lane), np.int64), np.full(len(lane), 8)
    done = []
    while len(lane):
        window = loads[p >> 3] >> (p & 7)
        entry = entries[begin + (window & mask)]
        symbol, bits = entry >> 4, entry & 15
        count = _RUN_BASE[symbol] + (window >> bits & _RUN_MASK[symbol])
        value = np.where(symbol < 16, symbol, np.where(symbol == 16, last, 0))
        done.append((lane, at, value, count))
        last = np.where((symbol < 16) & (symbol > 0), symbol, last)
        p = p + bits + _RUN_BITS[symbol]
        at, most = at + count, most - 1
        over = (at >= size) | (most <= 0)
        if over.any():
            if (at > size).any():
                raise ValueError("too many code lengths")
            after[lane[over]] = p[over]
            lane, at, last, most, p, size, begin, mask = (x[~over] for x in (lane, at, last, most, p, size, begin, mask))
    lane, at, value, count = (np.concatenate(x) for x in zip(*done))
    some = value > 0
    lane, at, value, count = lane[some], at[some], value[some], count[some]
    within = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
    lengths[np.repeat(lane, count), np.repeat(at, count) + within] = np.repeat(value, count)
    return lengths, after


def _read(asked: list[tuple[webp.Bits, int, int, bool]]) -> list[np.ndarray]:
    """Images with one group of codes each: all of them main ones, or none."""
    streams = [bits for bits, _, _, _ in asked]
    sizes = np.array([len(b.data) for b in streams])
    origin = 8 * (np.cumsum(sizes) - sizes)
    data = np.frombuffer(b"".join([*(b.data for b in streams), bytes(64)]), np.uint8)
    loads = np.ndarray((len(data) - 8,), "<i8", data, 0, (1,))  # 57 bits from any bit of a byte
    pos = origin + np.array([b.at for b in streams])
    window = loads[pos >> 3] >> (pos & 7)
    cache_bits = np.where(window & 1, window >> 1 & 15, 0)
    if (cache_bits > 11).any():
        raise ValueError("the colour cache is too large")
    pos = pos + np.where(window & 1, 5, 1) + np.array([main for _, _, _, main in asked])
    codes = []
    for i, size in enumerate(webp.ALPHABETS):
        alphabet = np.full(len(asked), size)
        if i == 0:
            alphabet += np.where(cache_bits, 1 << cache_bits, 0)
        lengths, pos = read_lengths(loads, pos, alphabet)
        codes.append(tables(lengths))
    totals = np.array([w * h for _, w, h, _ in asked])
    first = np.cumsum(totals) - totals
    widths, stop, apart = np.array([w for _, w, _, _ in asked]), origin + 8 * sizes, {}
    if asked[0][3]:
        pixels, tokens, pos, alone = _chains(loads, pos, stop, codes, first, totals, widths)
        apart = {i: webp.read_image(*asked[i]) for i in np.flatnonzero(alone).tolist()}
    else:
        pixels, tokens, pos = _tokens(loads, pos, codes, first, totals, widths)
    if (pos > stop).any():
        raise ValueError("the stream ends early")
    for i, at in enumerate((pos - origin).tolist()):
        if i not in apart:
            streams[i].at = at
    pixels = _resolve(pixels, tokens, cache_bits, first, totals)
    return [apart[i] if i in apart else pixels[a : a + n] for i, (a, n) in enumerate(zip(first.tolist(), totals.tolist()))]


def _still(codes) -> np.ndarray:
    """Whether an image has one colour, whose pixels take no bits."""
    green, begin, _ = codes[0]
    return np.all([longest == 0 for _, _, longest in codes[:4]], axis=0) & (green[begin] < 256 << 4)


def _colours(codes) -> np.ndarray:
    """Pixels of the first entries of the codes."""
    return sum((e[begin].astype(np.int64) >> 4) << up for (e, begin, _), up in zip(codes, (8, 16, 0, 24)))


def _reach(loads, pos, stop, codes, images):
    """Bits of the tokens that begin at each bit, for every place that an entry into one of ``images`` comes to, else 0;
    and the images whose entries do not meet soon."""
    reach = np.zeros(8 * len(loads) + 64, np.uint8)
    tables = []
    for i, (entries, begin, longest) in enumerate(codes):
        symbol, bits = entries >> 4, entries & 15
        if i == 0:  # bits and more bits of a length; 32: a distance follows, 64: a cached pixel
            copied = (symbol >= 256) & (symbol < 280)
            bits = bits + np.where(copied, 32 + webp.NUMBER_BITS[np.clip(symbol - 256, 0, 23)], 0) + np.where(symbol >= 280, 64, 0)
        elif i == 4:
            bits = bits + webp.NUMBER_BITS[symbol]
        if i in (0, 4) or longest[images].any():
            tables.append((bits.astype(np.uint8), begin, (1 << longest) - 1))
    many = -(-np.maximum(stop - pos, 0)[images] // SEGMENT)
    image = np.repeat(images, many)
    p = pos[image] + SEGMENT * (np.arange(len(image)) - np.repeat(np.cumsum(many) - many, many))
    state = np.array([image, stop[image], *(row[image] for _, begin, mask in tables for row in (begin, mask))])
    step = 0
    while len(p) and step < MOST_STEPS:
        for _ in range(STRIDE):
            window = loads[p >> 3] >> (p & 7)
            kind = tables[0][0][state[2] + (window & state[3])]
            after = p + (kind & 31)
            special = np.flatnonzero(kind > 31)
            q = after[special]
            window = loads[after >> 3] >> (after & 7)
            for i, (bits, _, _) in enumerate(tables[1:-1], 1):
                taken = bits[state[2 + 2 * i] + (window & state[3 + 2 * i])]
                after += taken
                window >>= taken
            if len(special):
                bits = tables[-1][0][state[-2, special] + (loads[q >> 3] >> (q & 7) & state[-1, special])]
                after[special] = q + np.where(kind[special] < 64, bits, 0)
            reach[p] = after - p
            p = np.minimum(after, state[1])
        step += STRIDE
        on = np.flatnonzero((p < state[1]) & (reach[p] == 0))
        p, state = p[on], state[:, on]
    return reach, np.unique(state[0])


def _leave(reach, p, stop):
    """Where chains from ``p`` first stand at ``stop`` or beyond."""
    out = p.copy()
    live = np.flatnonzero(out < stop)
    while len(live):
        at = out[live]
        at += reach[at]
        out[live] = at
        live = live[at < stop[live]]
    return out


def _mark(reach, pos, stop):
    """Adds 128 where the chains from ``pos`` to ``stop`` stand. Each segment's way out is the next one's way in. Chains
    that are not known after ``MOST_ROUNDS`` (entries met, but not the right ones) are left out, and which is returned."""
    many = -(-np.maximum(stop - pos, 0) // SEGMENT)
    first = np.cumsum(many) - many
    segment = np.arange(many.sum()) - np.repeat(first, many)
    begin = np.repeat(pos, many) + SEGMENT * segment
    end = np.minimum(begin + SEGMENT, np.repeat(stop, many))
    way_in, way_out = begin, _leave(reach, begin, end)
    lost = np.zeros(len(pos), bool)
    for _ in range(MOST_ROUNDS):
        now = np.where(segment > 0, np.roll(way_out, 1), begin)
        changed = np.flatnonzero(now != way_in)
        if not len(changed):
            break
        way_in = now
        way_out[changed] = _leave(reach, now[changed], end[changed])
    else:
        open_ends = np.where(segment > 0, np.roll(way_out, 1), begin) != way_in
        lost[np.repeat(np.arange(len(pos)), many)[open_ends]] = True
    live = np.flatnonzero((way_in < end) & ~np.repeat(lost, many))
    p, end = way_in[live], end[live]
    while len(p):
        bits = reach[p]
        reach[p] = bits | 128
        p = p + bits
        on = np.flatnonzero(p < end)
        p, end = p[on], end[on]
    return lost


def _chains(loads, pos, stop, codes, first, totals, widths):
    """As ``_tokens``, for streams that hold nothing else up to ``stop``; and which images have to be read one by one."""
    n, still = len(pos), _still(codes)
    green, begin, longest = codes[0]
    alone = ~still & (longest == 0) & (green[begin] >= 256 << 4)  # its tokens may take no bits
    reach, apart = _reach(loads, pos, stop, codes, np.flatnonzero(~still & ~alone))
    alone[apart] = True
    lanes = np.flatnonzero(~still & ~alone)
    lost = _mark(reach, pos[lanes], stop[lanes])
    alone[lanes[lost]] = True
    lanes = lanes[~lost]
    p = np.flatnonzero(reach > 127)
    of = np.repeat(np.arange(n), np.diff(np.searchsorted(p, stop), prepend=0))

    window = loads[p >> 3] >> (p & 7)
    entry = green[begin[of] + (window & ((1 << longest) - 1)[of])]
    symbol, q = entry >> 4, p + (entry & 15)
    copied = np.flatnonzero((symbol >= 256) & (symbol < 280))
    size, code, q1 = np.ones(len(p), np.int64), symbol[copied] - 256, q[copied]
    size[copied] = webp.NUMBER_BASE[code] + (loads[q1 >> 3] >> (q1 & 7) & webp.NUMBER_MASK[code])
    place = np.cumsum(size) - size
    count = np.bincount(of, minlength=n)
    place -= np.repeat(place[(np.cumsum(count) - count)[count > 0]], count[count > 0])
    kept = place < totals[of]  # the last byte's other bits are no tokens
    filled = np.bincount(of[kept], size[kept], n).astype(np.int64)
    wanted = np.where(still | alone, 0, totals)
    if (filled < wanted).any():
        raise ValueError("the stream ends early")
    if (filled > wanted).any():
        raise ValueError("a back-reference leaves the image")
    if not kept.all():
        copied = copied[kept[copied]]
        copied = (np.cumsum(kept) - 1)[copied]
        p, of, symbol, q, size, place = (x[kept] for x in (p, of, symbol, q, size, place))
    ends = pos.copy()
    ends[lanes] = (p + (reach[p] & 127))[np.cumsum(np.bincount(of, minlength=n))[lanes] - 1]

    back, code, q1, lane = np.zeros(len(p), np.int64), symbol[copied] - 256, q[copied], of[copied]
    entries, begin, longest = codes[4]
    q2 = q1 + webp.NUMBER_BITS[code]
    entry = entries[begin[lane] + (loads[q2 >> 3] >> (q2 & 7) & ((1 << longest) - 1)[lane])]
    code, q3 = entry >> 4, q2 + (entry & 15)
    number = webp.NUMBER_BASE[code] + (loads[q3 >> 3] >> (q3 & 7) & webp.NUMBER_MASK[code])
    near = webp.NEAR_STEPS[np.minimum(number, 120) - 1]
    back[copied] = np.where(number > 120, number - 120, np.maximum(1, near[:, 0] + near[:, 1] * widths[lane]))
    if (back > place).any():
        raise ValueError("a back-reference leaves the image")

    window = loads[q >> 3] >> (q & 7)
    value = (symbol.astype(np.uint32) & np.uint32(255)) << np.uint32(8)
    for (entries, begin, longest), up in zip(codes[1:4], (16, 0, 24)):
        entry = entries[begin[of] + (window & ((1 << longest) - 1)[of])]
        window >>= entry & 15
        value |= (entry >> 4).astype(np.uint32) << np.uint32(up)
    out = np.repeat(np.append(np.where(still, _colours(codes), 0), 0).astype(np.uint32), np.append(totals, 1))
    place += first[of]
    out[place] = value
    special = np.flatnonzero(symbol > 255)
    slot = symbol[special].astype(np.int64) - 280
    tokens = (place[special], size[special], back[special], np.where(slot < 0, -1, slot)) if len(special) else None
    return out, tokens, ends, alone


def _tokens(loads, pos, codes, first, totals, widths):
    """(literals at their places, (place, size, distance, slot) of the other tokens, where each stream ends)."""
    out, ends, others = np.zeros(int(totals.sum()) + 1, np.int64), pos.copy(), []
    # Symbols of a literal stand at their place in the pixel: green, red, blue, alpha.
    entries = [(e.astype(np.int64) >> 4) << (up + 4) | e & 15 for (e, _, _), up in zip(codes[:4], (8, 16, 0, 24))]
    far_entries, far_begin, far_longest = codes[4]
    still = _still(codes)
    if still.any():
        out[:-1] = np.repeat(np.where(still, _colours(codes), 0), totals)
    moving = np.flatnonzero(~still)
    # One row a quantity, so that images that end are taken out of all at once.
    rows = [moving, first[moving], (first + totals)[moving], widths[moving], far_begin[moving], (1 << far_longest[moving]) - 1]
    coded = [c for c in range(4) if c == 0 or (codes[c][2][moving] > 0).any()]
    for c in coded:
        rows += [codes[c][1][moving], (1 << codes[c][2][moving]) - 1]
    fixed = np.zeros(len(pos), np.int64)
    for c in range(4):
        if c not in coded:
            fixed |= entries[c][codes[c][1]]
    state = np.array([*rows, fixed[moving]])
    p, at = pos[moving], first[moving]
    while len(p):
        window = loads[p >> 3] >> (p & 7)
        green = entries[0][state[6] + (window & state[7])]
        after = p + (green & 15)
        value, taken = green | state[-1], green & 15
        window = loads[after >> 3] >> (after & 7)
        for i in range(1, len(coded)):
            entry = entries[coded[i]][state[6 + 2 * i] + (window & state[7 + 2 * i])]
            bits = entry & 15
            window = window >> bits
            value |= entry
            taken = taken + bits
        out[at] = value >> 4
        p = p + taken
        special = np.flatnonzero(green >= 256 << 12)
        step = 1
        if len(special):
            symbol, place, q = green[special] >> 12, at[special], after[special]
            size, back, slot = np.ones(len(special), np.int64), np.zeros(len(special), np.int64), np.full(len(special), -1)
            cached = symbol >= 280
            slot[cached] = symbol[cached] - 280
            c = np.flatnonzero(~cached)
            if len(c):
                lane, code, q1 = special[c], symbol[c] - 256, q[c]
                size[c] = webp.NUMBER_BASE[code] + (loads[q1 >> 3] >> (q1 & 7) & webp.NUMBER_MASK[code])
                q2 = q1 + webp.NUMBER_BITS[code]
                entry = far_entries[state[4, lane] + (loads[q2 >> 3] >> (q2 & 7) & state[5, lane])]
                code, q3 = entry >> 4, q2 + (entry & 15)
                number = webp.NUMBER_BASE[code] + (loads[q3 >> 3] >> (q3 & 7) & webp.NUMBER_MASK[code])
                near = webp.NEAR_STEPS[np.minimum(number, 120) - 1]
                back[c] = np.where(number > 120, number - 120, np.maximum(1, near[:, 0] + near[:, 1] * state[3, lane]))
                if (back[c] > place[c] - state[1, lane]).any():
                    raise ValueError("a back-reference leaves the image")
                q[c] = q3 + webp.NUMBER_BITS[code]
            p[special] = q
            others.append((place, size, back, slot))
            step = np.ones(len(at), np.int64)
            step[special] = size
        at = at + step
        over = at >= state[2]
        if over.any():
            if (at > state[2]).any():
                raise ValueError("a back-reference leaves the image")
            ends[state[0, over]] = p[over]
            state, p, at = state[:, ~over], p[~over], at[~over]
    return out, [np.concatenate(x) for x in zip(*others)] if others else None, ends


def _resolve(pixels, tokens, cache_bits, first, totals):
    """Copies and cached pixels take the values of the pixels they point to."""
    pixels = pixels.astype(np.uint32)
    if tokens is None:
        return pixels
    n = len(pixels) - 1
    place, size, back, slot = tokens
    copied = back > 0
    source = np.arange(n + 1)
    count = size[copied]
    moved = np.repeat(place[copied], count) + np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
    source[moved] = moved - np.repeat(back[copied], count)
    _follow(source, moved)
    asked = slot >= 0
    if asked.any():
        # The slot of a literal follows from its value, that of a copy is its source's.
        lane = np.repeat(np.arange(len(totals)), totals)
        bits = cache_bits[lane]
        slots = ((pixels[:-1] * np.uint32(webp.CACHE_FACTOR)) >> (32 - bits).astype(np.uint32)).astype(np.int64)
        slots[place[asked]] = slot[asked]
        some = np.flatnonzero(bits)
        key = (lane[some] << 11 | slots[source[some]]) << 32 | some
        key.sort()
        order, group = key & 0xFFFFFFFF, key >> 32
        same = group[1:] == group[:-1]
        last = np.full(n + 1, n)  # the pixel last put into the slot; none is a zero pixel
        last[order[1:][same]] = order[:-1][same]
        source[place[asked]] = last[place[asked]]
        pixels[place[asked]] = 0
        pixels[n] = 0
        _follow(source, np.concatenate((moved, place[asked])))
    return pixels[source[:n]]


def _follow(source: np.ndarray, places: np.ndarray) -> None:
    """Pointers to earlier places, carried on to where they end."""
    while True:
        now = source[places]
        further = source[now]
        if (further == now).all():
            return
        source[places] = further
