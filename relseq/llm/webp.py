"""Lossless WebP: a decoder for the whole format, and an encoder that writes any mix of its tools.

``decode`` reads prefix codes, back-references, the colour cache and entropy-image groups, inverts the
predictor, cross-colour, subtract-green and palette transforms, and returns pixels. A literal is one look
into a wide window of bits; rows whose predictor looks upwards only are undone as arrays. Where every code of
an image is of one fixed width and there is nothing but literals, pixels are unpacked as arrays.

``encode`` writes any mix of the format's tools from a token list, with random modes and factors, and
``encode_flat`` images of 8 bits a sample; both serve to check the decoder. ``webp_writer`` holds the encoder
that stores media.
"""

from __future__ import annotations

import struct
from collections import Counter
from functools import lru_cache
from heapq import heapify, heappop, heappush

import numpy as np

SIDE = 1 << 14
# Fixed values of the format.
LENGTH_ORDER = (17, 18, 0, 1, 2, 3, 4, 5, 16, 6, 7, 8, 9, 10, 11, 12, 13, 14, 15)
NEAR = (
    (0, 1), (1, 0), (1, 1), (-1, 1), (0, 2), (2, 0), (1, 2), (-1, 2), (2, 1), (-2, 1), (2, 2), (-2, 2), (0, 3), (3, 0), (1, 3),
    (-1, 3), (3, 1), (-3, 1), (2, 3), (-2, 3), (3, 2), (-3, 2), (0, 4), (4, 0), (1, 4), (-1, 4), (4, 1), (-4, 1), (3, 3), (-3, 3),
    (2, 4), (-2, 4), (4, 2), (-4, 2), (0, 5), (3, 4), (-3, 4), (4, 3), (-4, 3), (5, 0), (1, 5), (-1, 5), (5, 1), (-5, 1), (2, 5),
    (-2, 5), (5, 2), (-5, 2), (4, 4), (-4, 4), (3, 5), (-3, 5), (5, 3), (-5, 3), (0, 6), (6, 0), (1, 6), (-1, 6), (6, 1), (-6, 1),
    (2, 6), (-2, 6), (6, 2), (-6, 2), (4, 5), (-4, 5), (5, 4), (-5, 4), (3, 6), (-3, 6), (6, 3), (-6, 3), (0, 7), (7, 0), (1, 7),
    (-1, 7), (5, 5), (-5, 5), (7, 1), (-7, 1), (4, 6), (-4, 6), (6, 4), (-6, 4), (2, 7), (-2, 7), (7, 2), (-7, 2), (3, 7), (-3, 7),
    (7, 3), (-7, 3), (5, 6), (-5, 6), (6, 5), (-6, 5), (8, 0), (4, 7), (-4, 7), (7, 4), (-7, 4), (8, 1), (8, 2), (6, 6), (-6, 6),
    (8, 3), (5, 7), (-5, 7), (7, 5), (-7, 5), (8, 4), (6, 7), (-6, 7), (7, 6), (-7, 6), (8, 5), (7, 7), (-7, 7), (8, 6), (8, 7),
)
NEAR_STEPS = np.array(NEAR)
CACHE_FACTOR = 0x1E35A7BD
#: Of a length or distance symbol: how many more bits, a mask for them, and its least number.
NUMBER_BITS = np.array([max(0, (s - 2) >> 1) for s in range(40)])
NUMBER_MASK = ((1 << NUMBER_BITS) - 1).astype(np.uint32)
NUMBER_BASE = np.array([s + 1 if s < 4 else ((2 + (s & 1)) << ((s - 2) >> 1)) + 1 for s in range(40)])
WINDOW = 1 << 15  # bytes decoded at a time
PREDICTOR, CROSS, GREEN, PALETTE = range(4)
ALPHABETS = (256 + 24, 256, 256, 256, 40)
_REVERSED = np.array([int(f"{i:08b}"[::-1], 2) for i in range(256)], np.uint8)
#: The 15 bits of a number in reverse.
REVERSED_BITS = (_REVERSED[np.arange(1 << 15) & 255].astype(np.int64) << 8 | _REVERSED[np.arange(1 << 15) >> 8]) >> 1


class Bits:
    """Least significant bit first, from ``at``."""

    def __init__(self, data: bytes, at: int = 0) -> None:
        self.data, self.at, self.end = data, at, 8 * len(data)

    def take(self, n: int) -> int:
        if not n:
            return 0
        if self.at + n > self.end:
            raise ValueError("the stream ends early")
        byte, shift = self.at >> 3, self.at & 7
        self.at += n
        return int.from_bytes(self.data[byte : byte + 5], "little") >> shift & ((1 << n) - 1)

    def peek(self, n: int) -> int:
        byte, shift = self.at >> 3, self.at & 7
        return int.from_bytes(self.data[byte : byte + 5], "little") >> shift & ((1 << n) - 1)


class Code:
    """A canonical prefix code by its lengths; one used symbol takes no bits."""

    def __init__(self, lengths) -> None:
        used = [(n, s) for s, n in enumerate(lengths) if n]
        self.lengths = lengths
        self.width = None  # bits of every symbol if all are alike and in natural order
        if not used:
            used = [(1, 0)]
        if len(used) == 1:
            self.only, self.longest, self.width = used[0][1], 0, 0
            return
        self.only, self.longest = None, max(n for n, _ in used)
        if sum(1 << (self.longest - n) for n, _ in used) != 1 << self.longest:
            raise ValueError("a prefix code is not complete")
        if {n for n, _ in used} == {self.longest} and [s for _, s in used] == list(range(1 << self.longest)):
            self.width = self.longest
        self.used = sorted(used)
        self.table: list[int] | None = None

    def entries(self) -> list[int]:
        """For every value of the next ``longest`` bits: symbol << 4 | bits of its code."""
        if self.only is not None:
            return [self.only << 4]
        if self.table is None:
            sizes, symbols = np.array(self.used).T
            natural = np.repeat(symbols << 4 | sizes, 1 << (self.longest - sizes))
            self.table = natural[REVERSED_BITS[: 1 << self.longest] >> (15 - self.longest)].tolist()
        return self.table

    def read(self, bits: Bits) -> int:
        if self.only is not None:
            return self.only
        entry = self.entries()[bits.peek(self.longest)]
        bits.at += entry & 15
        if bits.at > bits.end:
            raise ValueError("the stream ends early")
        return entry >> 4


@lru_cache(512)
def single(symbol: int) -> Code:
    """The code of one symbol, which takes no bits."""
    return Code([0] * symbol + [1])


def read_code(bits: Bits, size: int) -> Code:
    lengths = [0] * size
    if bits.take(1):
        two, wide = bits.take(1), bits.take(1)
        first = bits.take(8 if wide else 1)
        if not two:
            return single(first)
        lengths[first] = lengths[bits.take(8)] = 1
        return Code(lengths)
    meta = [0] * 19
    for i in range(4 + bits.take(4)):
        meta[LENGTH_ORDER[i]] = bits.take(3)
    by = Code(meta)
    most = 2 + bits.take(2 + 2 * bits.take(3)) if bits.take(1) else size
    if by.only is not None and by.only < 16:
        return Code([by.only] * min(most, size) + [0] * (size - min(most, size)))
    entries, mask = by.entries(), (1 << by.longest) - 1
    data, p, read = bits.data, bits.at, int.from_bytes
    at, last = 0, 8
    while at < size and most > 0:
        most -= 1
        window = read(data[p >> 3 : (p >> 3) + 4], "little") >> (p & 7)
        entry = entries[window & mask]
        n = entry & 15
        s = entry >> 4
        p += n
        if s < 16:
            if s:
                lengths[at] = last = s
            at += 1
            continue
        window >>= n
        if s == 16:
            value, n = last, 3 + (window & 3)
            p += 2
        elif s == 17:
            value, n = 0, 3 + (window & 7)
            p += 3
        else:
            value, n = 0, 11 + (window & 127)
            p += 7
        if at + n > size:
            raise ValueError("too many code lengths")
        if value:
            lengths[at : at + n] = [value] * n
        at += n
    if p > bits.end:
        raise ValueError("the stream ends early")
    bits.at = p
    return Code(lengths)


def read_number(bits: Bits, symbol: int) -> int:
    if symbol < 4:
        return symbol + 1
    extra = (symbol - 2) >> 1
    return ((2 + (symbol & 1)) << extra) + bits.take(extra) + 1


def _blocks(size: int, bits: int) -> int:
    return (size + (1 << bits) - 1) >> bits


def read_image(bits: Bits, width: int, height: int, main: bool = False) -> np.ndarray:
    """An entropy-coded image as uint32 ARGB, flat."""
    cache_bits = bits.take(4) if bits.take(1) else 0
    if cache_bits > 11:
        raise ValueError("the colour cache is too large")
    groups_at, step = None, 0
    if main and bits.take(1):
        step = bits.take(3) + 2
        groups_at = (read_image(bits, _blocks(width, step), _blocks(height, step)) >> 8 & 0xFFFF).reshape(-1, _blocks(width, step))
    cache_size = 1 << cache_bits if cache_bits else 0
    sizes = (ALPHABETS[0] + cache_size, *ALPHABETS[1:])
    groups = [[read_code(bits, n) for n in sizes] for _ in range(1 if groups_at is None else int(groups_at.max()) + 1)]
    if len(groups) == 1 and all(c.width in (0, 8) for c in groups[0][:4]) and (groups[0][0].width == 8 or groups[0][0].only < 256):
        return _unpack(bits, groups[0], width * height)
    if groups_at is None:
        return _decode_arrays(bits, groups[0], cache_bits, width, width * height)
    return _decode(bits, groups, groups_at, step, cache_bits, width, height)


def _unpack(bits: Bits, codes: list[Code], n: int) -> np.ndarray:
    live = [c for c in range(4) if codes[c].width]
    need = n * len(live)
    byte, shift = bits.at >> 3, bits.at & 7
    raw = np.frombuffer(bits.data, np.uint8, min(need + 1, len(bits.data) - byte), byte)
    if 8 * len(raw) - shift < 8 * need:
        raise ValueError("the stream ends early")
    if shift:
        wide = raw[:need].astype(np.uint16) >> shift
        after = raw[1 : need + 1].astype(np.uint16) << (8 - shift)
        wide[: len(after)] |= after
        raw = wide.astype(np.uint8)
    bits.at += 8 * need
    samples = _REVERSED[raw[:need]].reshape(n, len(live)) if live else np.zeros((n, 0), np.uint8)
    place = {0: 8, 1: 16, 2: 0, 3: 24}
    out = np.zeros(n, np.uint32)
    for c in range(4):
        out |= (samples[:, live.index(c)].astype(np.uint32) if c in live else np.uint32(codes[c].only)) << np.uint32(place[c])
    return out


def _decode_arrays(bits: Bits, codes: list[Code], cache_bits: int, width: int, total: int) -> np.ndarray:
    """An image with one group of codes. What a token would be and where the next one would begin is looked up for
    every bit of a window at once; following the chain from the first bit then gives the tokens. Copies and cached
    pixels become pointers to earlier pixels, which are followed together."""
    tables = [np.array(c.entries(), np.int32) for c in codes]
    masks = [np.uint32(len(t) - 1) for t in tables]
    data = np.frombuffer(bits.data + bytes(16), np.uint8)
    p, todo, tokens = bits.at, total, []
    while todo:
        base = p >> 3
        take = min(WINDOW, len(bits.data) - base, todo * 8 + 8)
        if take <= 0:
            raise ValueError("the stream ends early")
        loads = np.ndarray((take + 8,), "<u4", data, base, (1,))
        ahead = (loads[:, None] >> np.arange(8, dtype=np.uint32)).ravel()  # 25 bits from every bit
        n = 8 * take
        green = tables[0][ahead[:n] & masks[0]]
        after = np.arange(n) + (green & 15)
        far = after
        for c in (1, 2, 3):
            if len(tables[c]) > 1:
                far = far + (tables[c] & 15).astype(np.uint8)[ahead[far] & masks[c]]
        special = np.flatnonzero(green >= 4096)
        if len(special):
            symbol, q = green[special] >> 4, after[special]
            short = symbol >= 280
            q2 = q + np.where(short, 0, NUMBER_BITS[np.minimum(symbol - 256, 39)])
            entry = tables[4][ahead[q2] & masks[4]]
            if far is after:
                far = after.copy()
            far[special] = np.where(short, q, q2 + (entry & 15) + NUMBER_BITS[entry >> 4])
        chain, at, following = [], p & 7, far.tolist()
        for _ in range(todo):
            if at >= n:
                break
            chain.append(at)
            at = following[at]
        place = np.array(chain)
        symbol, q = green[place] >> 4, after[place]
        size, back, slot = np.ones(len(place), np.int64), np.zeros(len(place), np.int64), np.full(len(place), -1)
        copied = np.flatnonzero((symbol >= 256) & (symbol < 280))
        if len(copied):
            code, q1 = symbol[copied] - 256, q[copied]
            size[copied] = NUMBER_BASE[code] + (ahead[q1] & NUMBER_MASK[code])
            q2 = q1 + NUMBER_BITS[code]
            entry = tables[4][ahead[q2] & masks[4]]
            code, q3 = entry >> 4, q2 + (entry & 15)
            number = NUMBER_BASE[code] + (ahead[q3] & NUMBER_MASK[code])
            back[copied] = np.where(number > 120, number - 120, np.maximum(1, (NEAR_STEPS[:, 0] + NEAR_STEPS[:, 1] * width)[np.minimum(number, 120) - 1]))
        cached = symbol >= 280
        slot[cached] = symbol[cached] - 280
        value = (symbol & 255).astype(np.uint32) << np.uint32(8)
        for c, up in ((1, 16), (2, 0), (3, 24)):
            entry = tables[c][ahead[q] & masks[c]]
            value |= (entry >> 4).astype(np.uint32) << np.uint32(up)
            q = q + (entry & 15)
        filled = np.cumsum(size)
        used = int(np.searchsorted(filled, todo)) + 1
        if used > len(place):  # the image goes on in the next window
            used = len(place)
            p = 8 * base + at
        else:
            p = 8 * base + int(far[place[used - 1]])
        if filled[used - 1] > todo:
            raise ValueError("a back-reference leaves the image")
        todo -= int(filled[used - 1])
        tokens.append([x[:used] for x in (size, back, slot, value)])
    if p > bits.end:
        raise ValueError("the stream ends early")
    bits.at = p
    size, back, slot, value = tokens[0] if len(tokens) == 1 else [np.concatenate(x) for x in zip(*tokens)]
    if len(size) == total and not cache_bits:
        return value
    start = np.cumsum(size) - size
    if (back > start).any():
        raise ValueError("a back-reference leaves the image")
    source = np.arange(total + 1) - np.append(np.repeat(back, size), 0)
    pixels = np.zeros(total + 1, np.uint32)
    pixels[start] = value
    source = _follow(source)
    if cache_bits:
        # The slot of a literal follows from its value, that of a copy is its source's.
        slots = ((pixels * np.uint32(CACHE_FACTOR)) >> np.uint32(32 - cache_bits)).astype(np.int64)
        asked = slot >= 0
        slots[start[asked]] = slot[asked]
        slots = slots[source[:total]]
        order = np.argsort(slots, kind="stable")
        same = slots[order[1:]] == slots[order[:-1]]
        last = np.full(total, total)  # the pixel last put into the slot; none is a zero pixel
        last[order[1:][same]] = order[:-1][same]
        source[start[asked]] = last[start[asked]]
        pixels[start[asked]] = 0
        source = _follow(source)
    return pixels[source[:total]]


def _follow(source: np.ndarray) -> np.ndarray:
    """Pointers to earlier places, carried on to where they end."""
    while True:
        further = source[source]
        if (further == source).all():
            return source
        source = further


def _decode(bits: Bits, groups, groups_at, step: int, cache_bits: int, width: int, height: int) -> np.ndarray:
    total = width * height
    out: list[int] = []
    cache, cached = [0] * (1 << cache_bits), 0  # pixels before ``cached`` are in the cache
    shift = 32 - cache_bits
    data, p, read = bits.data + bytes(32), bits.at, int.from_bytes
    # Symbols of a literal stand at their place in the pixel: green, red, blue, alpha.
    tables = [[t for code, up in zip(codes, (0, 16, 0, 24)) for t in ([(e >> 4) << (up + 4) | e & 15 for e in code.entries()], (1 << code.longest) - 1)] for codes in groups]
    greens, green_mask, reds, red_mask, blues, blue_mask, alphas, alpha_mask = tables[0]
    far_code, append = groups[0][4], out.append
    at = left = 0  # ``left``: bits of the window not yet used
    while at < total:
        if groups_at is not None:
            g = int(groups_at[at // width >> step, at % width >> step])
            greens, green_mask, reds, red_mask, blues, blue_mask, alphas, alpha_mask = tables[g]
            far_code = groups[g][4]
        if left < 60:  # four codes of 15 bits
            window = read(data[p >> 3 : (p >> 3) + 32], "little") >> (p & 7)
            left = 249
        green = greens[window & green_mask]
        n = green & 15
        if green < 4096:
            window >>= n
            red = reds[window & red_mask]
            m = red & 15
            window >>= m
            blue = blues[window & blue_mask]
            k = blue & 15
            window >>= k
            alpha = alphas[window & alpha_mask]
            n += m + k
            if alpha & 15:
                window >>= alpha & 15
                n += alpha & 15
            p += n
            left -= n
            append((alpha | red | blue) >> 4 | (green >> 4) << 8)
            at += 1
            continue
        p += n
        left = 0
        s = green >> 4
        if s < 280:
            bits.at = p
            n = read_number(bits, s - 256)
            far = read_number(bits, far_code.read(bits))
            p = bits.at
            if far > 120:
                far -= 120
            else:
                dx, dy = NEAR[far - 1]
                far = max(1, dx + dy * width)
            if far > at or at + n > total:
                raise ValueError("a back-reference leaves the image")
            if far >= n:
                out += out[at - far : at - far + n]
            else:
                part = out[at - far :]
                out += (part * (n // far + 1))[:n]
            at += n
        else:
            for value in out[cached:]:
                cache[(CACHE_FACTOR * value & 0xFFFFFFFF) >> shift] = value
            cached = at
            append(cache[s - 280])
            at += 1
        if p > bits.end:
            raise ValueError("the stream ends early")
    if p > bits.end:
        raise ValueError("the stream ends early")
    bits.at = p
    return np.array(out, np.uint32)


def _halves(a, b):
    return (a + b) // 2


def predict(mode: int, left, top, top_right, top_left):
    """Guess from neighbours by a mode that treats every channel alike."""
    if mode < 5:
        return (left, top, top_right, top_left)[mode - 1]
    if mode == 5:
        return _halves(_halves(left, top_right), top)
    if mode < 10:
        a, b = ((left, top_left), (left, top), (top_left, top), (top, top_right))[mode - 6]
        return _halves(a, b)
    if mode == 10:
        return _halves(_halves(left, top_left), _halves(top, top_right))
    if mode == 12:
        return np.clip(left + top - top_left, 0, 255)
    mean = _halves(left, top)
    return np.clip(mean + np.trunc((mean - top_left) / 2).astype(int), 0, 255)


BLACK = np.array([0, 0, 0, 255])  # channels in memory order: blue, green, red, alpha
LEFTWARD = np.isin(np.arange(256), (1, 5, 6, 7, 10, 11, 12, 13))  # modes that look at the left neighbour


def _channels(argb: np.ndarray) -> np.ndarray:
    return np.ascontiguousarray(argb, "<u4").view(np.uint8).reshape(*argb.shape, 4)


def predictions(mode: int, left, top, top_right, top_left):
    """Guesses of one mode for arrays of pixels (channels last, signed)."""
    if mode == 0 or mode > 13:
        return np.broadcast_to(BLACK.astype(top.dtype), top.shape)
    if mode == 11:
        nearer = np.abs(top - top_left).sum(axis=-1, keepdims=True) < np.abs(left - top_left).sum(axis=-1, keepdims=True)
        return np.where(nearer, left, top)
    return predict(mode, left, top, top_right, top_left)


def neighbours(rows: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Left, top, top right and top left of every pixel but the first row and column (signed). The last pixel's
    top right neighbour is its own row's first one."""
    wide = rows.astype(np.int16)
    right = np.concatenate((wide[:-1, 2:], wide[1:, :1]), axis=1)
    return wide[1:, :-1], wide[:-1, 1:], right, wide[:-1, :-1]


def residuals(rows: np.ndarray, modes: np.ndarray, bits: int) -> np.ndarray:
    """Pixels less their guesses; rows: height x width x 4."""
    height, width, _ = rows.shape
    out = rows.copy()
    out[0, 1:] -= rows[0, :-1]
    out[0, 0] -= BLACK.astype(np.uint8)
    out[1:, 0] -= rows[:-1, 0]
    if height > 1 and width > 1:
        around = neighbours(rows)
        each = modes[np.arange(1, height)[:, None] >> bits, np.arange(1, width)[None, :] >> bits]
        for mode in np.unique(each):
            guess = predictions(int(mode), *around).astype(np.uint8)
            out[1:, 1:] = np.where((each == mode)[..., None], rows[1:, 1:] - guess, out[1:, 1:])
    return out


def undo_predictor(rows: np.ndarray, modes: np.ndarray, bits: int) -> np.ndarray:
    """Residuals back to pixels: whole rows at a time, left to right only where a mode looks to the left."""
    height, width, _ = rows.shape
    out = np.empty((height, width, 4), np.uint8)
    out[0] = np.cumsum(rows[0], axis=0, dtype=np.uint8) + BLACK.astype(np.uint8)
    out[:, 0] = np.cumsum(np.concatenate((out[:1, 0], rows[1:, 0])), axis=0, dtype=np.uint8)
    if width == 1:
        return out
    tile = np.arange(1, width) >> bits
    whole = np.ascontiguousarray(rows).view("<u4")[..., 0]
    y = 1
    while y < height:
        line = modes[y >> bits]
        end = min(height, ((y >> bits) + 1) << bits)
        if ((line == 0) | (line > 13)).all():  # nothing here depends on other pixels
            np.add(whole[y:end, 1:], np.uint32(0xFF000000), out=out.view("<u4")[y:end, 1:, 0])  # black, and alpha's carry falls off
            y = end
            continue
        each = line[tile]
        kinds = np.unique(each)
        ahead = ~LEFTWARD[kinds].any()
        while y < end:
            up = np.concatenate((out[y - 1], out[y : y + 1, 0])).astype(np.int16)
            top, right, corner = up[1:-1], up[2:], up[:-2]
            if len(kinds) == 1 and kinds[0] == 1:
                out[y, 1:] = np.cumsum(rows[y, 1:], axis=0, dtype=np.uint8) + out[y, 0]
            elif ahead:
                guess = predictions(int(kinds[0]), top, top, right, corner)
                for mode in kinds[1:]:
                    guess = np.where((each == mode)[:, None], predictions(int(mode), top, top, right, corner), guess)
                out[y, 1:] = rows[y, 1:] + guess.astype(np.uint8)
            else:
                left = out[y, 0].astype(np.int16)
                for x in range(width - 1):
                    guess = predictions(int(each[x]), left, top[x], right[x], corner[x])
                    left = (rows[y, x + 1] + guess) & 255
                    out[y, x + 1] = left
            y += 1
    return out


def cross_colour(rows: np.ndarray, factors: np.ndarray, bits: int, inverse: bool) -> np.ndarray:
    height, width, _ = rows.shape
    y, x = np.mgrid[:height, :width]
    f = _channels(factors)[y >> bits, x >> bits].view(np.int8).astype(int)
    to_red, green_to_blue, red_to_blue = f[..., 0], f[..., 1], f[..., 2]
    signed = rows.view(np.int8).astype(int)
    out = rows.astype(int)
    sign = 1 if inverse else -1
    new_red = (out[..., 2] + sign * (to_red * signed[..., 1] >> 5)) % 256
    true_red = (new_red if inverse else out[..., 2]).astype(np.uint8).view(np.int8).astype(int)
    out[..., 0] = (out[..., 0] + sign * (green_to_blue * signed[..., 1] >> 5) + sign * (red_to_blue * true_red >> 5)) % 256
    out[..., 2] = new_red
    return out.astype(np.uint8)


def subtract_green(rows: np.ndarray, inverse: bool) -> np.ndarray:
    out = rows.copy()
    for c in (0, 2):
        out[..., c] = out[..., c] + out[..., 1] if inverse else out[..., c] - out[..., 1]
    return out


def _bundle(colours: int) -> int:
    return 3 if colours <= 2 else 2 if colours <= 4 else 1 if colours <= 16 else 0


def steps(data: bytes):
    """Decodes the content of a lossless chunk to height x width uint32 ARGB, leaving the entropy-coded images to the
    caller: each is asked for as (bits, width, height, main) and expected as flat pixels, with ``bits`` moved on."""
    bits = Bits(data)
    if bits.take(8) != 0x2F:
        raise ValueError("not a lossless image")
    width, height = bits.take(14) + 1, bits.take(14) + 1
    bits.take(1)
    if bits.take(3):
        raise ValueError("an unknown version")
    undo, seen, inner = [], set(), width
    while bits.take(1):
        kind = bits.take(2)
        if kind in seen:
            raise ValueError("a transform occurs twice")
        seen.add(kind)
        if kind in (PREDICTOR, CROSS):
            size = bits.take(3) + 2
            part = (yield bits, _blocks(inner, size), _blocks(height, size), False).reshape(-1, _blocks(inner, size))
            undo.append((kind, inner, size, part))
        elif kind == GREEN:
            undo.append((kind, inner, 0, None))
        else:
            colours = bits.take(8) + 1
            table = np.cumsum(_channels((yield bits, colours, 1, False)), axis=0, dtype=np.uint8).view("<u4").ravel()
            undo.append((kind, inner, _bundle(colours), table))
            inner = _blocks(inner, _bundle(colours))
    argb = (yield bits, inner, height, True).reshape(height, inner)
    for kind, wide, size, part in reversed(undo):
        if kind == PALETTE:
            index = argb >> 8 & 0xFF
            if size:
                each = 8 >> size
                index = (index[..., None] >> (np.arange(1 << size, dtype=np.uint32) * each) & ((1 << each) - 1)).reshape(height, -1)[:, :wide]
            argb = np.where(index < len(part), part[np.minimum(index, len(part) - 1)], 0).astype(np.uint32)
            continue
        rows = _channels(argb)
        if kind == PREDICTOR:
            rows = undo_predictor(rows, part >> 8 & 0xFF, size)
        elif kind == CROSS:
            rows = cross_colour(rows, part, size, True)
        else:
            rows = subtract_green(rows, True)
        argb = np.ascontiguousarray(rows).view("<u4")[..., 0]
    return argb


def content(data: bytes) -> bytes:
    """The lossless chunk of a file."""
    if data[:4] != b"RIFF" or data[8:16] != b"WEBPVP8L":
        raise ValueError("not a simple lossless file")
    return data[20 : 20 + struct.unpack("<I", data[16:20])[0]]


def samples(argb: np.ndarray) -> np.ndarray:
    """height x width x 4: red, green, blue, alpha."""
    return _channels(argb)[..., [2, 1, 0, 3]]


def decode(data: bytes) -> np.ndarray:
    """A file -> height x width x 4 samples: red, green, blue, alpha."""
    run = steps(content(data))
    try:
        asked = next(run)
        while True:
            asked = run.send(read_image(*asked))
    except StopIteration as done:
        return samples(done.value)


def files(data: bytes):
    """The files that stand one after the other in ``data``."""
    at = 0
    while at < len(data):
        size = 8 + struct.unpack("<I", data[at + 4 : at + 8])[0]
        yield data[at : at + size]
        at += size


class Writer:
    def __init__(self) -> None:
        self.value, self.n = 0, 0

    def put(self, value: int, n: int) -> None:
        self.value |= value << self.n
        self.n += n

    def bytes(self) -> bytes:
        return self.value.to_bytes((self.n + 7) // 8, "little")


def _file(stream: bytes) -> bytes:
    odd = b"\0" * (len(stream) % 2)
    return b"RIFF" + struct.pack("<I", 12 + len(stream) + len(odd)) + b"WEBPVP8L" + struct.pack("<I", len(stream)) + stream + odd


def _head(width: int, height: int, alpha: bool) -> Writer:
    w = Writer()
    for value, n in ((0x2F, 8), (width - 1, 14), (height - 1, 14), (int(alpha), 1), (0, 3)):
        w.put(value, n)
    return w


def _flat_code(w: Writer, listed: int) -> None:
    """256 symbols of 8 bits each, ``listed`` (12 to 19) code-length lengths written."""
    w.put(0, 1)
    w.put(listed - 4, 4)
    for s in LENGTH_ORDER[:listed]:
        w.put(int(s == 8), 3)
    w.put(1, 1)  # 256 lengths are given, the rest is 0
    w.put(3, 3)
    w.put(254, 8)


def flat_header(width: int, height: int) -> bytes:
    """Everything before the samples, padded to whole bytes by listing more code lengths."""
    for extra in range(8):
        w = _head(width, height, False)
        w.put(0, 1)  # no transform
        w.put(0, 1)  # no colour cache
        w.put(0, 1)  # one group of codes
        _flat_code(w, 12 + extra)
        _flat_code(w, 12)
        _flat_code(w, 12)
        for symbol in (255, 0):  # alpha and distance: one symbol
            w.put(1, 1)
            w.put(0, 1)
            w.put(1, 1)
            w.put(symbol, 8)
        if w.n % 8 == 0:
            return w.bytes()
    raise AssertionError


def encode_flat(rgb: np.ndarray) -> bytes:
    """height x width x 3 samples -> a file in which every sample takes 8 bits."""
    height, width, _ = rgb.shape
    return _file(flat_header(width, height) + _REVERSED[rgb[..., [1, 0, 2]]].tobytes())


def code_lengths(counts: Counter, size: int, most: int = 15) -> list[int]:
    """Lengths of a prefix code for ``counts``, none above ``most``."""
    out = [0] * size
    live = {s: c for s, c in counts.items() if c}
    if len(live) == 1:
        out[next(iter(live))] = 1
        return out
    floor = 0
    while live:
        heap = [(max(c, floor), i, (s,)) for i, (s, c) in enumerate(sorted(live.items()))]
        heapify(heap)
        depth = dict.fromkeys(live, 0)
        fresh = len(heap)
        while len(heap) > 1:
            a, b = heappop(heap), heappop(heap)
            for s in a[2] + b[2]:
                depth[s] += 1
            heappush(heap, (a[0] + b[0], fresh, a[2] + b[2]))
            fresh += 1
        if max(depth.values()) <= most:
            for s, n in depth.items():
                out[s] = n
            return out
        floor = 2 * floor + 1 + sum(live.values()) // (1 << most)
    return out


def _write_code(w: Writer, lengths: list[int]) -> dict[int, tuple[int, int]]:
    """Header of a code; returns symbol -> (bits reversed for the stream, how many)."""
    used = [s for s, n in enumerate(lengths) if n]
    if len(used) <= 1 and (not used or used[0] < 256):
        symbol = used[0] if used else 0
        w.put(1, 1)
        w.put(0, 1)
        w.put(1, 1)
        w.put(symbol, 8)
        return {symbol: (0, 0)}
    meta = code_lengths(Counter(lengths), 19, 7)
    by = _bit_codes(meta)
    w.put(0, 1)
    w.put(15, 4)
    for s in LENGTH_ORDER:
        w.put(meta[s], 3)
    w.put(0, 1)
    for n in lengths:
        w.put(*by[n])
    return {used[0]: (0, 0)} if len(used) == 1 else _bit_codes(lengths)


def _bit_codes(lengths: list[int]) -> dict[int, tuple[int, int]]:
    used = sorted((n, s) for s, n in enumerate(lengths) if n)
    if len(used) == 1:
        return {used[0][1]: (0, 0)}
    out, code, last = {}, 0, used[0][0] if used else 0
    for n, s in used:
        code <<= n - last
        last = n
        out[s] = (int(f"{code:0{n}b}"[::-1], 2), n)
        code += 1
    return out


def _number_symbol(value: int) -> tuple[int, int, int]:
    """(symbol, extra bits' value, how many) of a length or distance code."""
    if value <= 4:
        return value - 1, 0, 0
    v = value - 1
    top = v.bit_length() - 1
    half = v >> (top - 1) & 1
    return 2 * top + half, v - ((2 + half) << (top - 1)), top - 1


def tokens(argb: np.ndarray, width: int, cache_bits: int = 0, references: bool = False):
    """('pixel', value), ('copy', length, distance) and ('cache', index) for a flat image."""
    flat = [int(v) for v in argb.ravel()]
    last: dict[tuple[int, int, int], int] = {}
    cache: dict[int, int] = {}
    at = 0
    while at < len(flat):
        key = tuple(flat[at : at + 3])
        n = 1
        if references and len(key) == 3 and (was := last.get(key)) is not None:
            n = 0
            while at + n < len(flat) and n < 4096 and flat[was + n] == flat[at + n]:
                n += 1
            yield ("copy", n, at - was)
        else:
            i = (CACHE_FACTOR * flat[at] & 0xFFFFFFFF) >> (32 - cache_bits) if cache_bits else -1
            yield ("cache", i) if cache_bits and cache.get(i) == flat[at] else ("pixel", flat[at])
        for k in range(at, at + n):
            last[tuple(flat[k : k + 3])] = k
            if cache_bits:
                cache[(CACHE_FACTOR * flat[k] & 0xFFFFFFFF) >> (32 - cache_bits)] = flat[k]
        at += n


def write_image(w: Writer, argb: np.ndarray, main: bool = False, cache_bits: int = 0, references: bool = False, group_bits: int = 0) -> None:
    """An entropy-coded image. ``group_bits``: blocks of that size take turns with two groups of codes."""
    height, width = argb.shape
    w.put(int(cache_bits > 0), 1)
    if cache_bits:
        w.put(cache_bits, 4)
    group_of = np.zeros((1, 1), np.uint32)
    if main:
        w.put(int(group_bits > 0), 1)
        if group_bits:
            rows, cols = _blocks(height, group_bits), _blocks(width, group_bits)
            group_of = (np.add.outer(np.arange(rows), np.arange(cols)) % 2).astype(np.uint32)
            w.put(group_bits - 2, 3)
            write_image(w, group_of << 8)
    shift = group_bits or 14
    plan, at = [], 0
    counts = [[Counter() for _ in range(5)] for _ in range(int(group_of.max()) + 1)]
    for t in tokens(argb, width, cache_bits, references):
        g = int(group_of[at // width >> shift, at % width >> shift])
        if t[0] == "pixel":
            parts = [(c, t[1] >> s & 0xFF, 0, 0) for c, s in enumerate((8, 16, 0, 24))]
        elif t[0] == "cache":
            parts = [(0, 280 + t[1], 0, 0)]
        else:
            a, b = _number_symbol(t[1]), _number_symbol(t[2] + 120)
            parts = [(0, 256 + a[0], *a[1:]), (4, *b)]
        for c, s, *_ in parts:
            counts[g][c][s] += 1
        plan.append((g, parts))
        at += t[1] if t[0] == "copy" else 1
    sizes = (ALPHABETS[0] + ((1 << cache_bits) if cache_bits else 0), *ALPHABETS[1:])
    codes = [[_write_code(w, code_lengths(c, n)) for c, n in zip(group, sizes)] for group in counts]
    for g, parts in plan:
        for c, s, extra, n in parts:
            w.put(*codes[g][c][s])
            w.put(extra, n)


def encode(rgba: np.ndarray, transforms: tuple[int, ...] = (), cache_bits: int = 0, references: bool = False, group_bits: int = 0, size: int = 2, seed: int = 0) -> bytes:
    """height x width x 4 samples -> a file with the given transforms (in this order) and tools. Modes of the
    predictor and factors of the cross-colour transform are drawn from ``seed``."""
    draw = np.random.default_rng(seed)
    argb = np.ascontiguousarray(rgba[..., [2, 1, 0, 3]]).view("<u4")[..., 0]
    height, width = argb.shape
    w = _head(width, height, True)
    for kind in transforms:
        inner = argb.shape[1]
        w.put(1, 1)
        w.put(kind, 2)
        rows = _channels(argb)
        if kind in (PREDICTOR, CROSS):
            shape = _blocks(height, size), _blocks(inner, size)
            w.put(size - 2, 3)
            if kind == PREDICTOR:
                part = draw.integers(0, 14, shape, np.uint32) << np.uint32(8) | np.uint32(0xFF000000)
                rows = residuals(rows, part >> 8 & 0xFF, size)
            else:
                part = draw.integers(0, 1 << 24, shape, np.uint32) | np.uint32(0xFF000000)
                rows = cross_colour(rows, part, size, False)
            write_image(w, part)
        elif kind == GREEN:
            rows = subtract_green(rows, False)
        else:
            table, index = np.unique(argb, return_inverse=True)
            if len(table) > 256:
                raise ValueError("too many colours for a palette")
            w.put(len(table) - 1, 8)
            deltas = np.diff(_channels(table.astype(np.uint32)), axis=0, prepend=np.zeros((1, 4), np.uint8))
            write_image(w, np.ascontiguousarray(deltas).view("<u4").reshape(1, -1))
            fold = _bundle(len(table))
            index = index.reshape(height, inner).astype(np.uint32)
            wide = _blocks(inner, fold)
            index = np.pad(index, ((0, 0), (0, (wide << fold) - inner))).reshape(height, wide, 1 << fold)
            argb = (index << (np.arange(1 << fold, dtype=np.uint32) * (8 >> fold))).sum(axis=2, dtype=np.uint32) << np.uint32(8) | np.uint32(0xFF000000)
            continue
        argb = np.ascontiguousarray(rows).view("<u4")[..., 0]
    w.put(0, 1)
    write_image(w, argb, True, cache_bits, references, group_bits)
    return _file(w.bytes())
