"""Lossless WebP: a decoder of the whole published format, and encoders.

The decoder reads prefix codes (simple and normal), meta prefix codes, back-references, the colour cache, and inverts the predictor,
cross-colour, subtract-green and palette transforms. `decode` takes one file and goes symbol by symbol. `decode_many` takes many: images without
colour cache and with one symbol each for red, blue and alpha are read side by side, a symbol of each in a step of array operations,
and their back-references are followed together afterwards; all others go through `decode`.

Payloads are kept as 8-bit grey samples, `SEGMENT` bytes an image, so a payload of any length is a list of small images. Each image gets the
transforms that its samples ask for (subtract-green alone, a predictor after it, or a palette with several pixels bundled in one), back-references,
one or two groups of prefix codes, and Huffman codes for the symbols as well as for the lengths of the codes. Two means of the format can't shorten
a grey image: once red, blue and alpha have one symbol each, an entry of the colour cache only splits a green symbol in two, and after subtract-green a
cross-colour transform has nothing left to take away.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from . import common as C, tokens as T

#: Bytes of payload in an image.
SEGMENT = 4096
#: Samples a row of a payload's image; payloads are a multiple of it.
ROW = 64
#: Images read side by side, which bounds the memory of `decode_many`.
LANES = 2048
#: Images written together, which bounds the memory of `encode_grey`.
TOGETHER = 512
#: Fewest bytes a back-reference of a payload's image stands for.
LEAST = 5
#: Longest code in a payload's image, which bounds the tables of `decode_many`.
LONGEST = 12
#: Rows (as a power of two) of the blocks that share a group of codes.
BLOCK = 4
#: Fixed values of the format: the order in which the lengths of the code-length code stand.
LENGTH_ORDER = (17, 18, 0, 1, 2, 3, 4, 5, 16, 6, 7, 8, 9, 10, 11, 12, 13, 14, 15)
PREDICTOR, CROSS_COLOUR, SUBTRACT_GREEN, PALETTE = range(4)
#: Short distances, nearest first: 120 places (x to the left, y above) of a half plane.
NEAR = sorted(((x, y) for y in range(8) for x in range(-7, 9) if y or x > 0), key=lambda p: (p[0] ** 2 + p[1] ** 2, -p[1], -p[0]))


class Bits:
    """Reads bits, lowest first."""

    def __init__(self, data: bytes, at: int = 0):
        self.data, self.at = data + bytes(8), at

    def peek(self, n: int) -> int:
        b = self.at >> 3
        return int.from_bytes(self.data[b : b + 9], "little") >> (self.at & 7) & (1 << n) - 1

    def take(self, n: int) -> int:
        v = self.peek(n)
        self.at += n
        return v


class Code:
    """A canonical prefix code."""

    def __init__(self, lengths: np.ndarray):
        self.lengths = lengths
        self.symbols = np.flatnonzero(lengths)
        if not len(self.symbols):
            raise ValueError("a prefix code without symbols")
        n = lengths[self.symbols]
        self.width = 0 if len(n) == 1 else int(n.max())
        if len(n) > 1 and int((1 << self.width - n).sum()) != 1 << self.width:
            raise ValueError("an incomplete prefix code")
        self.table: list[tuple[int, int]] = []

    def _fill(self) -> None:
        """The symbol and length for each value of the next `width` bits."""
        self.table = [(int(self.symbols[0]), 0)] * (1 << self.width)
        code, last = 0, 0
        for n, s in sorted((int(self.lengths[s]), int(s)) for s in self.symbols) if self.width else ():
            code <<= n - last
            first = int(f"{code:0{n}b}"[::-1], 2)
            self.table[first :: 1 << n] = [(s, n)] * (1 << self.width - n)
            code, last = code + 1, n

    def read(self, b: Bits) -> int:
        if not self.table:
            self._fill()
        s, n = self.table[b.peek(self.width)]
        b.at += n
        return s


@lru_cache(1024)
def _simple(size: int, one: int, other: int) -> Code:
    lengths = np.zeros(size, np.int64)
    lengths[[one, other]] = 1
    return Code(lengths)


@lru_cache(4096)
def _lengths_code(count: int, bits: int) -> Code:
    """The code of code lengths, whose own lengths have three bits each."""
    inner = np.zeros(19, np.int64)
    for i in range(count):
        inner[LENGTH_ORDER[i]] = bits >> 3 * i & 7
    code = Code(inner)
    code._fill()
    return code


def read_code(b: Bits, size: int) -> Code:
    if b.take(1):
        two = b.take(1)
        one = b.take(8 if b.take(1) else 1)
        return _simple(size, one, b.take(8) if two else one)
    lengths = np.zeros(size, np.int64)
    count = 4 + b.take(4)
    code = _lengths_code(count, b.peek(3 * count))
    b.at += 3 * count
    left = min(size, 2 + b.take(2 + 2 * b.take(3)) if b.take(1) else size)
    table, mask, out, last = code.table, (1 << code.width) - 1, [], 8
    bits = int.from_bytes(b.data[b.at >> 3 : (b.at >> 3) + 2 * left + 8], "little") >> (b.at & 7)  # at most 7 + 7 bits each
    at = 0
    while len(out) < size and left:
        left -= 1
        s, n = table[bits >> at & mask]
        at += n
        if s < 16:
            out.append(s)
            last = s or last
        elif s == 16:
            out += [last] * (3 + (bits >> at & 3))
            at += 2
        elif s == 17:
            out += [0] * (3 + (bits >> at & 7))
            at += 3
        else:
            out += [0] * (11 + (bits >> at & 127))
            at += 7
    if len(out) > size:
        raise ValueError("too many code lengths")
    b.at += at
    lengths[: len(out)] = out
    return Code(lengths)


def _value(b: Bits, s: int) -> int:
    """A length or distance from its prefix symbol and extra bits."""
    if s < 4:
        return s + 1
    extra = s - 2 >> 1
    return ((2 + (s & 1)) << extra) + b.take(extra) + 1


def _read_codes(b: Bits, width: int, height: int, main: bool) -> tuple[int, list[list[int]] | None, int, list[list[Code]]]:
    """What stands before the pixels of an entropy-coded image: bits of the colour cache, meta codes and their shift, groups of codes."""
    cache_bits = b.take(4) if b.take(1) else 0
    meta, shift = None, 0
    if main and b.take(1):
        shift = b.take(3) + 2
        meta = (read_pixels(b, -(-width >> shift), -(-height >> shift), False).reshape(-(-height >> shift), -1) >> 8 & 0xFFFF).tolist()
    sizes = (280 + (1 << cache_bits if cache_bits else 0), 256, 256, 256, 40)
    groups = [[read_code(b, n) for n in sizes] for _ in range(1 + max(map(max, meta)) if meta else 1)]
    return cache_bits, meta, shift, groups


def read_pixels(b: Bits, width: int, height: int, main: bool) -> np.ndarray:
    """ARGB pixels of an entropy-coded image."""
    return _read_symbols(b, width, width * height, *_read_codes(b, width, height, main))


def _read_symbols(b: Bits, width: int, n: int, cache_bits: int, meta: list[list[int]] | None, shift: int, groups: list[list[Code]]) -> np.ndarray:
    out = [0] * n
    cache = [0] * (1 << cache_bits)
    i = 0
    while i < n:
        green, red, blue, alpha, dist = groups[meta[i // width >> shift][i % width >> shift] if meta else 0]
        s = green.read(b)
        if s < 256:
            out[i] = s << 8 | red.read(b) << 16 | blue.read(b) | alpha.read(b) << 24
            end = i + 1
        elif s < 280:
            length = _value(b, s - 256)
            d = _value(b, dist.read(b))
            if d <= 120:
                x, y = NEAR[d - 1]
                d = max(1, x + y * width)
            else:
                d -= 120
            end = i + length
            if d > i or end > n:
                raise ValueError("a back-reference leaves the image")
            for k in range(i, end):
                out[k] = out[k - d]
        else:
            out[i] = cache[s - 280]
            end = i + 1
        if cache_bits:
            for k in range(i, end):
                cache[(0x1E35A7BD * out[k] & 0xFFFFFFFF) >> 32 - cache_bits] = out[k]
        i = end
    return np.array(out, np.uint32)


#: Lowest value and extra bits of each prefix symbol of a length or distance.
EXTRA = np.array([max(s - 2 >> 1, 0) for s in range(40)])
LOWEST = np.array([s + 1 if s < 4 else ((2 + (s & 1)) << (s - 2 >> 1)) + 1 for s in range(40)])


@lru_cache(16)
def _reversed(n: int) -> np.ndarray:
    """The numbers below 2**n with their bits turned around."""
    out = np.zeros(1, np.int64)
    for k in range(n):
        out = np.concatenate([out, out + (1 << n - 1 - k)])
    return out


def _lookup(code: Code) -> np.ndarray:
    """For each value of the next `width` bits: 16 times the symbol, plus the length."""
    n = code.lengths[code.symbols] if code.width else np.zeros(1, np.int64)
    order = np.argsort(n, kind="stable")
    return np.repeat(code.symbols[order] << 4 | n[order], 1 << code.width - n[order])[_reversed(code.width)].astype(np.uint16)


def _side_by_side(lanes: list[tuple[Bits, int, int, list[list[Code]], list[list[int]] | None, int]]) -> list[np.ndarray]:
    """ARGB pixels of images (bits, width, pixels, groups of codes, meta codes and their shift) of which green and distances alone have codes of more than
    one symbol. All have meta codes, or none."""
    streams = [x[0].data[x[0].at >> 3 :] for x in lanes]
    raw = np.frombuffer(b"".join(streams) + bytes(8), np.uint8)
    window = raw[:-7].astype(np.int64)  # the 56 bits from each byte on
    for k in range(1, 7):
        window |= raw[k : k - 7].astype(np.int64) << 8 * k
    at = 8 * np.cumsum([0] + [len(x) for x in streams[:-1]]) + [x[0].at & 7 for x in lanes]
    last = len(window) - 1
    tables, places, size = [], {}, 0
    firsts = []
    for g in (g for x in lanes for g in x[3]):
        for c in (g[0], g[4]):
            if id(c) not in places:
                places[id(c)] = size
                tables.append(_lookup(c))
                size += len(tables[-1])
            firsts.append((places[id(c)], (1 << c.width) - 1))
    table = np.concatenate(tables)
    of_group = np.array(firsts).reshape(-1, 4).T  # first place and mask of green, of distances
    group = np.cumsum([0] + [len(x[3]) for x in lanes[:-1]])
    green, green_mask, far, far_mask = of_group[:, group]
    meta = None
    if lanes[0][4] is not None:
        meta = np.concatenate([np.ravel(x[4]) + g for x, g in zip(lanes, group.tolist())])
        across = np.array([len(x[4][0]) for x in lanes])
        block = np.cumsum([0] + [len(x[4]) * len(x[4][0]) for x in lanes[:-1]])
        shift = np.array([x[5] for x in lanes])
    width, count = (np.array([x[k] for x in lanes]) for k in (1, 2))
    end = np.cumsum(count)
    begin = end - count
    near = np.array(NEAR).T
    value = np.zeros(int(end[-1]), np.uint8)
    copies = []
    live = np.arange(len(lanes))
    i = begin.copy()
    while len(live):
        if meta is not None:
            y, x = np.divmod(i - begin[live], width)
            green, green_mask, far, far_mask = of_group[:, meta[block[live] + (y >> shift[live]) * across[live] + (x >> shift[live])]]
        w = window[at >> 3] >> (at & 7)
        e = table[green + (w & green_mask)].astype(np.int64)
        s, n = e >> 4, e & 15
        value[i] = s & 255  # a copy's own is never looked at
        step = np.ones(len(live), np.int64)
        k = np.flatnonzero(s >= 256)
        if len(k):
            p = s[k] - 256
            step[k] = length = LOWEST[p] + (w[k] >> n[k] & (1 << EXTRA[p]) - 1)
            to = at[k] + n[k] + EXTRA[p]
            w = window[np.minimum(to >> 3, last)] >> (to & 7)
            e = table[far[k] + (w & far_mask[k])].astype(np.int64)
            p = e >> 4
            d = LOWEST[p] + (w >> (e & 15) & (1 << EXTRA[p]) - 1)
            x, y = near[:, np.minimum(d, 120) - 1]
            d = np.where(d > 120, d - 120, np.maximum(x + y * width[k], 1))
            if (d > i[k] - begin[live[k]]).any() or (i[k] + length > end[live[k]]).any():
                raise ValueError("a back-reference leaves the image")
            copies.append((i[k], length, d))
            at[k] = to + (e & 15) + EXTRA[p]
            n[k] = 0
        at += n
        i += step
        on = i < end[live]
        if not on.all():
            live, at, i, green, far, green_mask, far_mask, width = (v[on] for v in (live, at, i, green, far, green_mask, far_mask, width))
        at = np.minimum(at, 8 * last + 7)
    if copies:
        start, length, d = (np.concatenate(x) for x in zip(*copies))
        to = np.arange(int(length.sum())) + np.repeat(start - (np.cumsum(length) - length), length)
        source = np.arange(len(value), dtype=np.int32)
        source[to] -= np.repeat(d, length).astype(np.int32)
        while len(to):  # twice as far back in each turn
            new = source[source[to]]
            moved = new != source[to]
            source[to] = new
            to = to[moved]
        value = value[source]
    same = [int(g[1].symbols[0]) << 16 | int(g[2].symbols[0]) | int(g[3].symbols[0]) << 24 for g in (x[3][0] for x in lanes)]
    return np.split(value.astype(np.uint32) << np.uint32(8) | np.repeat(np.array(same, np.uint32), count), end[:-1])


def _split(p: int) -> tuple[int, int, int, int]:
    return p >> 24, p >> 16 & 255, p >> 8 & 255, p & 255


def _join(c) -> int:
    return c[0] << 24 | c[1] << 16 | c[2] << 8 | c[3]


def _mean(a: int, b: int) -> int:
    return ((a ^ b) >> 1 & 0x7F7F7F7F) + (a & b)


def _clamped(f, *pixels: int) -> int:
    return _join([min(255, max(0, f(*c))) for c in zip(*map(_split, pixels))])


def _select(left: int, top: int, corner: int) -> int:
    a = sum(abs(t - c) for t, c in zip(_split(top), _split(corner)))
    b = sum(abs(x - c) for x, c in zip(_split(left), _split(corner)))
    return left if a < b else top


#: Prediction of a pixel from its left, top, top-right and top-left neighbours, by mode.
MODES = (
    lambda a, t, r, c: 0xFF000000, lambda a, t, r, c: a, lambda a, t, r, c: t, lambda a, t, r, c: r, lambda a, t, r, c: c,
    lambda a, t, r, c: _mean(_mean(a, r), t), lambda a, t, r, c: _mean(a, c), lambda a, t, r, c: _mean(a, t), lambda a, t, r, c: _mean(c, t), lambda a, t, r, c: _mean(t, r),
    lambda a, t, r, c: _mean(_mean(a, c), _mean(t, r)), lambda a, t, r, c: _select(a, t, c), lambda a, t, r, c: _clamped(lambda x, y, z: x + y - z, a, t, c),
    lambda a, t, r, c: _clamped(lambda m, z: m + int((m - z) / 2), _mean(a, t), c),
)


def _predict(modes: list[list[int]], shift: int, p: list[int], i: int, width: int) -> int:
    x, y = i % width, i // width
    if not y:
        return p[i - 1] if x else 0xFF000000
    if not x:
        return p[i - width]
    return MODES[modes[y >> shift][x >> shift]](p[i - 1], p[i - width], p[i - width + 1], p[i - width - 1])


def _add(a: int, b: int) -> int:
    return (a & 0xFF00FF00) + (b & 0xFF00FF00) & 0xFF00FF00 | (a & 0x00FF00FF) + (b & 0x00FF00FF) & 0x00FF00FF


def _subtract(a: int, b: int) -> int:
    return _join([x - y & 255 for x, y in zip(_split(a), _split(b))])


def _modes(image: np.ndarray, across: int) -> list[list[int]]:
    return [[m if m < len(MODES) else 0 for m in row] for row in (image.reshape(-1, across) >> 8 & 15).tolist()]


def _signed(x: np.ndarray) -> np.ndarray:
    return x.astype(np.uint8).astype(np.int8).astype(np.int32)


def _colours(image: np.ndarray, shift: int, width: int, height: int, pixels: np.ndarray, sign: int) -> np.ndarray:
    """Adds (decoding) or subtracts what green says of red and blue, and red of blue."""
    t = np.repeat(np.repeat(image.reshape(-(-height >> shift), -1), 1 << shift, 0), 1 << shift, 1)[:height, :width].ravel()
    green, red, blue = _signed(pixels >> 8 & 255), pixels >> 16 & 255, pixels & 255
    new = red.astype(np.int32) + sign * (_signed(t & 255) * green >> 5) & 255
    by_red = _signed(new if sign > 0 else red)
    low = blue.astype(np.int32) + sign * ((_signed(t >> 8 & 255) * green >> 5) + (_signed(t >> 16 & 255) * by_red >> 5)) & 255
    return pixels & np.uint32(0xFF00FF00) | new.astype(np.uint32) << np.uint32(16) | low.astype(np.uint32)


def _sums(p: np.ndarray, height: int, left: bool) -> np.ndarray:
    """Pixels from what a predictor that is the left neighbour everywhere, or the top one, has left of them."""
    q = p.reshape(height, -1, 1).view(np.uint8).copy()  # a channel each
    q[0, 0] += np.array([0xFF000000], np.uint32).view(np.uint8)
    if left:
        q[:, 0] = np.cumsum(q[:, 0], 0, dtype=np.uint8)
    else:
        q[0] = np.cumsum(q[0], 0, dtype=np.uint8)
    return np.cumsum(q, 1 if left else 0, dtype=np.uint8).view(np.uint32).ravel()


def _open(data: bytes) -> tuple[Bits, int, int, list, int]:
    """Bits of a lossless WebP file up to its main image, width and height, transforms to undo, and the main image's width."""
    if data[:4] != b"RIFF" or data[8:12] != b"WEBP":
        raise ValueError("not a WebP file")
    at = 12
    while data[at : at + 4] != b"VP8L":
        if at + 8 > len(data):
            raise ValueError("no lossless image")
        at += 8 + (struct.unpack_from("<I", data, at + 4)[0] + 1 & ~1)
    if at + 8 > len(data):
        raise ValueError("no lossless image")
    size = struct.unpack_from("<I", data, at + 4)[0]
    b = Bits(data[at + 8 : at + 8 + size])
    if b.take(8) != 0x2F:
        raise ValueError("no lossless signature")
    width, height = b.take(14) + 1, b.take(14) + 1
    b.take(1)
    if b.take(3):
        raise ValueError("unknown version")
    todo, across = [], width
    while b.take(1):
        kind = b.take(2)
        if kind in (PREDICTOR, CROSS_COLOUR):
            shift = b.take(3) + 2
            todo.append((kind, across, shift, read_pixels(b, -(-across >> shift), -(-height >> shift), False)))
        elif kind == PALETTE:
            n = b.take(8) + 1
            table = read_pixels(b, n, 1, False).tolist()
            for i in range(1, n):
                table[i] = _add(table[i], table[i - 1])
            pack = 3 if n <= 2 else 2 if n <= 4 else 1 if n <= 16 else 0
            todo.append((kind, across, pack, np.array(table + [0] * (256 - n), np.uint32)))
            across = -(-across >> pack)
        else:
            todo.append((kind, across, 0, None))
    return b, width, height, todo, across


def _undo(p: np.ndarray, height: int, todo: list) -> np.ndarray:
    """ARGB pixels before the transforms."""
    for kind, across, shift, image in reversed(todo):
        if kind == PREDICTOR:
            modes = _modes(image, -(-across >> shift))
            if {m for row in modes for m in row} in ({1}, {2}):
                p = _sums(p, height, modes[0][0] == 1)
                continue
            q = p.tolist()
            for i in range(len(q)):
                q[i] = _add(q[i], _predict(modes, shift, q, i, across))
            p = np.array(q, np.uint32)
        elif kind == CROSS_COLOUR:
            p = _colours(image, shift, across, height, p, 1)
        elif kind == SUBTRACT_GREEN:
            g = p >> 8 & 255
            p = p & np.uint32(0xFF00FF00) | ((p >> 16) + g & 255) << np.uint32(16) | p + g & 255
        else:
            index = (p >> 8 & 255).reshape(height, -1)
            if shift:
                each = 8 >> shift
                index = np.stack([index >> np.uint32(each * k) & np.uint32((1 << each) - 1) for k in range(1 << shift)], 2).reshape(height, -1)[:, :across]
            p = image[index].ravel()
    return p


def decode(data: bytes) -> np.ndarray:
    """RGBA samples (height, width, 4) of a lossless WebP file."""
    b, width, height, todo, across = _open(data)
    return _samples(_undo(read_pixels(b, across, height, True), height, todo), width, height)


def _samples(p: np.ndarray, width: int, height: int) -> np.ndarray:
    return np.stack([p >> 16 & 255, p >> 8 & 255, p & 255, p >> 24], 1).astype(np.uint8).reshape(height, width, 4)


def decode_many(files: list[bytes]) -> list[tuple[np.ndarray, int, int]]:
    """ARGB pixels, width and height of each of some lossless WebP files."""
    out: list = [None] * len(files)
    for first in range(0, len(files), LANES):
        lanes, rest = ([], []), ([], [])
        for k in range(first, min(first + LANES, len(files))):
            b, width, height, todo, across = _open(files[k])
            codes = cache_bits, meta, shift, groups = _read_codes(b, across, height, True)
            if cache_bits or any(c.width or c.symbols[0] != d.symbols[0] for g in groups for c, d in zip(g[1:4], groups[0][1:4])):
                out[k] = _undo(_read_symbols(b, across, across * height, *codes), height, todo), width, height
            else:
                lanes[meta is not None].append((b, across, across * height, groups, meta, shift))
                rest[meta is not None].append((k, width, height, todo))
        for some, those in zip(lanes, rest):
            for (k, width, height, todo), p in zip(those, _side_by_side(some) if some else ()):
                out[k] = _undo(p, height, todo), width, height
    return out


class Writer:
    """Collects bits, lowest first."""

    def __init__(self):
        self.value, self.n = 0, 0

    def put(self, v: int, n: int) -> None:
        self.value |= v << self.n
        self.n += n

    def bytes(self) -> bytes:
        return self.value.to_bytes(-(-self.n // 8), "little")


def container(stream: bytes) -> bytes:
    chunk = b"VP8L" + struct.pack("<I", len(stream)) + stream + bytes(len(stream) % 2)
    return b"RIFF" + struct.pack("<I", 4 + len(chunk)) + b"WEBP" + chunk


def _head(w: Writer, width: int, height: int) -> None:
    w.put(0x2F, 8)
    w.put(width - 1, 14)
    w.put(height - 1, 14)
    w.put(1, 1)
    w.put(0, 3)


# ---- an encoder that can use all of the format ----


def _lengths(counts: list[int], most: int = 15) -> list[int]:
    """Lengths of a complete prefix code; small counts are raised until none exceeds `most`."""
    used = [s for s, c in enumerate(counts) if c]
    if len(used) < 2:
        return [int(bool(c)) for c in counts]
    floor, k = 1, len(used)
    while True:
        leaves = sorted((max(counts[s], floor), s) for s in used)
        weight, above = [c for c, _ in leaves], [0] * (2 * k - 1)
        leaf, node = 0, k  # joined nodes come in ascending order of weight, so both queues are sorted
        for new in range(k, 2 * k - 1):
            total = 0
            for _ in range(2):
                if leaf < k and (node == new or weight[leaf] <= weight[node]):
                    at, leaf = leaf, leaf + 1
                else:
                    at, node = node, node + 1
                total += weight[at]
                above[at] = new
            weight.append(total)
        depth = [0] * (2 * k - 1)
        for at in range(2 * k - 3, -1, -1):
            depth[at] = depth[above[at]] + 1
        if max(depth) <= most:
            out = [0] * len(counts)
            for (_, s), n in zip(leaves, depth):
                out[s] = n
            return out
        floor *= 2


def _codes(lengths: list[int]) -> list[tuple[int, int]]:
    out, code, last = [(0, 0)] * len(lengths), 0, 0
    used = sorted((n, s) for s, n in enumerate(lengths) if n)
    if len(used) == 1:
        return out
    for n, s in used:
        code <<= n - last
        out[s] = int(f"{code:0{n}b}"[::-1], 2), n
        code, last = code + 1, n
    return out


def _put_code(w: Writer, counts: list[int]) -> list[tuple[int, int]]:
    used = [s for s, c in enumerate(counts) if c] or [0]
    if len(used) <= 2 and used[-1] < 256:
        w.put(1, 1)
        w.put(len(used) - 1, 1)
        w.put(1, 1)
        for s in used:
            w.put(s, 8)
        return _codes([int(s in used) for s in range(len(counts))])
    lengths = _lengths(counts)
    if len(used) == 1:
        lengths = [int(s == used[0]) for s in range(len(counts))]
    runs, i = [], 0
    while i < len(lengths):
        n = next((k for k in range(i, len(lengths)) if lengths[k] != lengths[i]), len(lengths)) - i
        v = lengths[i]
        i += n
        if v:
            runs.append((v, 0, 0))
            n -= 1
        while n:
            if v == 0 and n >= 11:
                t = min(n, 138)
                runs.append((18, t - 11, 7))
            elif v == 0 and n >= 3:
                t = min(n, 10)
                runs.append((17, t - 3, 3))
            elif v and n >= 3:
                t = min(n, 6)
                runs.append((16, t - 3, 2))
            else:
                t = 1
                runs.append((v, 0, 0))
            n -= t
    inner = [0] * 19
    for s, _, _ in runs:
        inner[s] += 1
    il = _lengths(inner, 7)
    ic = _codes(il)
    w.put(0, 1)
    count = max(4, 1 + max(i for i, s in enumerate(LENGTH_ORDER) if il[s]))
    w.put(count - 4, 4)
    for s in LENGTH_ORDER[:count]:
        w.put(il[s], 3)
    w.put(0, 1)
    for s, v, n in runs:
        w.put(*ic[s])
        w.put(v, n)
    return _codes(lengths)


def _prefix(v: int) -> tuple[int, int, int]:
    """Prefix symbol, extra bits and their number of a length or distance."""
    v -= 1
    if v < 4:
        return v, 0, 0
    top = v.bit_length() - 1
    half = v >> top - 1 & 1
    return 2 * top + half, v & (1 << top - 1) - 1, top - 1


def _put_pixels(w: Writer, p: list[int], width: int, main: bool, cache_bits: int = 0, references: bool = False, meta_shift: int = 0) -> None:
    height = len(p) // width
    w.put(int(cache_bits > 0), 1)
    if cache_bits:
        w.put(cache_bits, 4)
    across, kinds = -(-width >> meta_shift) if meta_shift else 1, 1
    if main:
        w.put(int(meta_shift > 0), 1)
        if meta_shift:
            w.put(meta_shift - 2, 3)
            blocks = [(x + y) % 2 << 8 for y in range(-(-height >> meta_shift)) for x in range(across)]
            _put_pixels(w, blocks, across, False)
            kinds += max(blocks) >> 8
    near = {max(1, x + y * width): i + 1 for i, (x, y) in reversed(list(enumerate(NEAR)))}
    cache, seen, ops, i = [None] * (1 << cache_bits), {}, [], 0
    while i < len(p):
        n, d = 0, 0
        if references and i + 3 <= len(p):
            j = seen.get(tuple(p[i : i + 3]))
            if j is not None:
                while i + n < len(p) and n < 4096 and p[j + n] == p[i + n]:
                    n += 1
                d = i - j
        slot = lambda q: (0x1E35A7BD * q & 0xFFFFFFFF) >> 32 - cache_bits
        if n >= 3:
            ops.append((i, "copy", n, near.get(d, d + 120)))
        elif cache_bits and cache[slot(p[i])] == p[i]:
            n = 1
            ops.append((i, "cache", slot(p[i]), 0))
        else:
            n = 1
            ops.append((i, "plain", p[i], 0))
        for k in range(i, i + n):
            seen[tuple(p[k : k + 3])] = k
            if cache_bits:
                cache[slot(p[k])] = p[k]
        i += n
    sizes = (280 + (1 << cache_bits if cache_bits else 0), 256, 256, 256, 40)
    groups = [[[0] * n for n in sizes] for _ in range(kinds)]
    coded = []
    for i, kind, a, d in ops:
        g = ((i % width >> meta_shift) + (i // width >> meta_shift)) % 2 if main and meta_shift else 0
        if kind == "plain":
            syms = [(0, a >> 8 & 255, 0, 0), (1, a >> 16 & 255, 0, 0), (2, a & 255, 0, 0), (3, a >> 24, 0, 0)]
        elif kind == "cache":
            syms = [(0, 280 + a, 0, 0)]
        else:
            s, e = _prefix(a), _prefix(d)
            syms = [(0, 256 + s[0], *s[1:]), (4, *e)]
        coded.append((g, syms))
        for c, s, _, _ in syms:
            groups[g][c][s] += 1
    codes = [[_put_code(w, c) for c in g] for g in groups]
    for g, syms in coded:
        for c, s, v, n in syms:
            w.put(*codes[g][c][s])
            w.put(v, n)


def encode(rgba: np.ndarray, transforms: tuple[int, ...] = (), cache_bits: int = 0, references: bool = True, meta_shift: int = 0, shift: int = 3) -> bytes:
    """A lossless WebP of (height, width, 4) samples with any of the format's means, for small images."""
    height, width = rgba.shape[:2]
    q = rgba.reshape(-1, 4).astype(np.uint32)
    p = q[:, 3] << 24 | q[:, 0] << 16 | q[:, 1] << 8 | q[:, 2]
    w = Writer()
    _head(w, width, height)
    across = width
    for kind in transforms:
        w.put(1, 1)
        w.put(kind, 2)
        if kind == PALETTE:
            table = np.unique(p)
            n = len(table)
            pack = 3 if n <= 2 else 2 if n <= 4 else 1 if n <= 16 else 0
            w.put(n - 1, 8)
            t = table.tolist()
            _put_pixels(w, [t[0]] + [_subtract(b, a) for a, b in zip(t, t[1:])], n, False)
            index = np.searchsorted(table, p).reshape(height, across)
            wide = -(-across >> pack)
            full = np.zeros((height, wide << pack), np.int64)
            full[:, :across] = index
            each = 8 >> pack
            p = (sum(full[:, k :: 1 << pack] << each * k for k in range(1 << pack)) << 8).ravel().astype(np.uint32) if pack else (index.ravel() << 8).astype(np.uint32)
            across = wide
        elif kind == SUBTRACT_GREEN:
            g = p >> 8 & 255
            p = p & np.uint32(0xFF00FF00) | ((p >> 16) - g & 255) << np.uint32(16) | p - g & 255
        else:
            cols, rows = -(-across >> shift), -(-height >> shift)
            w.put(shift - 2, 3)
            if kind == PREDICTOR:
                image = np.array([(k % len(MODES)) << 8 for k in range(cols * rows)], np.uint32)
                modes, old = _modes(image, cols), p.tolist()
                p = np.array([_subtract(x, _predict(modes, shift, old, i, across)) for i, x in enumerate(old)], np.uint32)
            else:
                image = np.array([(k * 37 & 255) << 16 | (k * 11 & 255) << 8 | k * 5 & 255 for k in range(cols * rows)], np.uint32)
                p = _colours(image, shift, across, height, p, -1)
            _put_pixels(w, image.tolist(), cols, False)
    w.put(0, 1)
    _put_pixels(w, p.tolist(), across, True, cache_bits, references, meta_shift)
    return container(w.bytes())


# ---- payloads as media columns ----


def payload(text: str) -> bytes:
    b = text.encode()
    return b + bytes(-len(b) % 64 or (0 if b else 64))


def _repeats(a: np.ndarray, image: np.ndarray, begin: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Back-references within images that stand one after another, each beginning where the last has ended or later: places, lengths and distances."""
    n = len(a) - 3
    b = a.astype(np.int64)
    p = np.flatnonzero(image[:n] == image[3:])
    key = image[p] << 44 | (b[p] | b[p + 1] << 8 | b[p + 2] << 16 | b[p + 3] << 24) << 12 | p - begin[image[p]]
    key.sort()
    four, p = key >> 12, begin[key >> 44] + (key & 4095)
    same = np.flatnonzero(four[1:] == four[:-1])  # the nearest earlier four equal bytes
    d = np.zeros(n + 1, np.int64)
    d[p[same + 1]] = p[same + 1] - p[same]
    edge = np.flatnonzero(np.diff(d, prepend=0))  # runs of one distance are one match
    stop = np.append(edge, n)[1:] + 3
    enough = (d[edge] > 0) & (stop - edge >= LEAST)
    out, last = [], 0
    for p, e, q in zip(edge[enough].tolist(), stop[enough].tolist(), d[edge[enough]].tolist()):
        if p < last:
            p = last
        if e - p >= LEAST:
            out += p, e - p, q
            last = e
    return tuple(np.array(out, np.int64).reshape(-1, 3).T)


@lru_cache(2)
def _value_symbols(most: int) -> np.ndarray:
    """Prefix symbol, extra bits and their number of the values up to `most`."""
    return np.array([_prefix(max(v, 1)) for v in range(most + 1)]).T


@lru_cache(4)
def _distance_codes(width: int, most: int) -> np.ndarray:
    """The number that stands for a distance: its place among the short ones, or 120 more than itself."""
    out = np.arange(most + 1) + 120
    for i, (x, y) in reversed(list(enumerate(NEAR))):
        out[max(1, x + y * width)] = i + 1
    return out


def _huffman(counts: np.ndarray, most: int) -> tuple[np.ndarray, np.ndarray]:
    """Huffman lengths of prefix codes, one code a row, and the codes, turned around. Codes get two symbols at least; in those with a length above `most`
    small counts are raised until none is."""
    few = np.flatnonzero((counts > 0).sum(1) < 2)
    if len(few):
        counts = counts.copy()
        for s in (0, 1):
            counts[few, s] += (counts[few] > 0).sum(1) < 2
            few = few[(counts[few] > 0).sum(1) < 2]
    n = _depths(counts)
    floor = 1
    while len(deep := np.flatnonzero(n.max(1, initial=0) > most)):
        floor *= 2
        n[deep] = _depths(np.where(counts[deep], np.maximum(counts[deep], floor), 0))
    order = np.argsort(np.where(n, n, 99), 1, kind="stable")
    m = np.take_along_axis(n, order, 1)
    room = np.where(m, 1 << most - m, 0)
    codes = np.zeros_like(n)
    np.put_along_axis(codes, order, _reversed(most)[np.cumsum(room, 1) - room & (1 << most) - 1], 1)
    return n, codes


def _depths(counts: np.ndarray) -> np.ndarray:
    """Depth of each symbol (0 for unused ones) in the Huffman tree of each row, which has two used symbols at least; a step joins two nodes in all rows."""
    k, size = counts.shape
    used = (counts > 0).sum(1)
    rows = np.argsort(-used, kind="stable")  # those with most symbols first, so that the rows of a step are the first ones
    used = used[rows]
    order = np.argsort(np.where(counts[rows] > 0, counts[rows], 1 << 40), 1, kind="stable")
    size += 1  # a place behind the leaves, and behind the nodes, that is never taken
    weight = np.full((k, 2 * size), 1 << 40)
    weight[:, : size - 1] = np.take_along_axis(counts[rows], order, 1)
    weight[:, :size][np.arange(size) >= used[:, None]] = 1 << 40
    above = np.zeros(k * 2 * size, np.int64)
    weight, base = weight.ravel(), np.arange(k) * 2 * size
    leaf, node = base.copy(), base + size
    joins = [int(x) for x in np.searchsorted(-used, -np.arange(2, int(used.max(initial=1)) + 1), "right")]  # rows with so many symbols
    for j, r in enumerate(joins):
        a, b, new = leaf[:r], node[:r], base[:r] + size + j
        total = 0
        for _ in range(2):
            x, y = weight[a], weight[b]
            low = x <= y
            above[np.where(low, a, b)] = new
            total = total + np.where(low, x, y)
            a += low
            b += ~low
        weight[new] = total
    depth = np.zeros(k * 2 * size, np.int64)
    for j in range(len(joins) - 2, -1, -1):
        at = base[: joins[j + 1]] + size + j
        depth[at] = depth[above[at]] + 1
    depth = np.where(np.arange(size - 1) < used[:, None], depth[above].reshape(k, 2 * size)[:, : size - 1] + 1, 0)
    out = np.zeros(counts.shape, np.int64)
    out[rows[:, None], order] = depth
    return out


def _length_tokens(n: np.ndarray) -> tuple[np.ndarray, ...]:
    """The code lengths of each row in runs, as (row, place, symbol, extra value, extra bits)."""
    turn = np.ones(n.shape, bool)
    turn[:, 1:] = n[:, 1:] != n[:, :-1]
    row, at = np.nonzero(turn)
    v = n[row, at]
    left = np.diff(np.append(row * n.shape[1] + at, n.size))
    none = np.zeros_like(row)
    some = v > 0
    out = [(row[some], at[some], v[some], none[some], none[some])]
    at, left = at + some, left - some
    while len(row):
        zero = v == 0
        z = np.minimum(left, np.where(zero, 138, 6))
        s = np.select([zero & (z > 10), zero & (z > 2), z > 2], [18, 17, 16], v)
        run = z > 2
        x, m = np.select([s == 18, run], [z - 11, z - 3], 0), np.select([s == 18, s == 17, run], [7, 3, 2], 0)
        z = np.where(run, z, np.minimum(z, 1))
        go = z > 0
        out.append((row[go], at[go], s[go], x[go], m[go]))
        row, at, left, v = row[go], (at + z)[go], (left - z)[go], v[go]
    return tuple(map(np.concatenate, zip(*out)))


def _put_lengths(n: np.ndarray) -> tuple[tuple[np.ndarray, ...], tuple[np.ndarray, ...]]:
    """The lengths of each row's code as tokens: the code of code lengths as (value, bits) a row, and the lengths as (row, place, value, bits)."""
    row, at, s, x, m = _length_tokens(n)
    inner, codes = _huffman(np.bincount(row * 19 + s, minlength=19 * len(n)).reshape(-1, 19), 7)
    inner_in_order = inner[:, LENGTH_ORDER]
    count = np.maximum(19 - (inner_in_order[:, ::-1] > 0).argmax(1), 4)
    value = count - 4 << 1 | (inner_in_order << 3 * np.arange(19)).sum(1) << 5
    return (value, 6 + 3 * count), (row, at, codes[row, s] | x << inner[row, s], inner[row, s] + m)


@lru_cache(2)
def _plog(most: int) -> np.ndarray:
    """x times its logarithm, for x up to `most`."""
    x = np.arange(most + 1.0)
    return x * np.log2(np.maximum(x, 1))


def _cost(counts: np.ndarray) -> np.ndarray:
    """Bits that symbols of these counts take by their entropy (a bit each at least, where they differ), and nearly those of their code; the symbols stand
    along the last axis."""
    p, n, used = _plog(SEGMENT), counts.sum(-1), (counts > 0).sum(-1)
    return np.maximum(p[n] - p[counts].sum(-1), np.where(used > 1, n, 0)) + 6 * used


#: Forms of a payload's image: grey samples, what the left or the top neighbour says of them less, or indices into a palette.
GREY, LEFT, TOP, INDEXED = range(4)


def _bundled(a: np.ndarray) -> tuple[np.ndarray, tuple[int, ...], int]:
    """Samples of at most 16 values as indices, several in a pixel; the values, and the logarithm of how many."""
    values = np.unique(a)
    pack = 3 if len(values) <= 2 else 2 if len(values) <= 4 else 1
    index = np.searchsorted(values, a).astype(np.uint8).reshape(-1, 1 << pack)
    return (index << (8 >> pack) * np.arange(1 << pack, dtype=np.uint8)).sum(1, dtype=np.uint8), tuple(values.tolist()), pack


def _forms(images: list[np.ndarray]) -> list[tuple[int, np.ndarray, int, tuple[int, ...]]]:
    """The form of each image that takes the fewest bits by entropy: which it is, its pixels, the logarithm of how many samples they have, and the palette."""
    size = np.array([len(a) for a in images])
    k, rows = len(images), np.concatenate(images).reshape(-1, ROW)
    head = (np.cumsum(size) - size) // ROW
    left, top = rows.copy(), rows.copy()
    left[:, 1:] -= rows[:, :-1]
    top[1:] -= rows[:-1]
    top[head] = left[head]
    left[:, 0] = top[:, 0]
    image = np.repeat(np.arange(k) << 8, size)
    counts = [np.bincount(image + x.ravel(), minlength=k << 8).reshape(k, 256) for x in (rows, left, top)]
    bits = np.stack([_cost(c) for c in counts], 1) + [0, 100, 100]
    best = bits.argmin(1)
    few = (counts[0] > 0).sum(1) <= 16
    begin = head * ROW
    out = []
    for i, (a, form, n) in enumerate(zip(images, best.tolist(), size.tolist())):
        if few[i]:
            pixels, values, pack = _bundled(a)
            if _cost(np.bincount(pixels)) + 50 + 12 * len(values) < bits[i, form]:
                out.append((INDEXED, pixels, pack, values))
                continue
        out.append((form, (rows, left, top)[form].ravel()[begin[i] : begin[i] + n], 0, ()))
    return out


@lru_cache(4096)
def _lead(form: int, height: int, values: tuple[int, ...], cut: int) -> tuple[tuple[int, int], ...]:
    """What stands before the codes of an image, as values of at most 48 bits: its head, the transforms, and the meta codes (from block row `cut` on the second group)."""
    w = Writer()
    _head(w, ROW, height)
    w.put(1, 1)
    if form == INDEXED:
        w.put(PALETTE, 2)
        w.put(len(values) - 1, 8)
        t = [0xFF000000 | v << 16 | v << 8 | v for v in values]
        _put_pixels(w, t[:1] + [_subtract(y, x) for x, y in zip(t, t[1:])], len(t), False)
    else:
        w.put(SUBTRACT_GREEN, 2)
    if form in (LEFT, TOP):
        w.put(1, 1)
        w.put(PREDICTOR, 2)
        w.put(7, 3)  # one block
        _put_pixels(w, [form << 8], 1, False)
    w.put(0, 2)  # no other transform, no colour cache
    w.put(int(cut > 0), 1)
    if cut:
        w.put(BLOCK - 2, 3)
        across = ROW >> BLOCK
        _put_pixels(w, [int(y >= cut) << 8 for y in range(-(-height >> BLOCK)) for _ in range(across)], across, False)
    return tuple((w.value >> i & (1 << 48) - 1, min(48, w.n - i)) for i in range(0, w.n, 48))


def _cuts(counts: np.ndarray) -> np.ndarray:
    """From which block row on the symbols of each image (image, block row, symbol) get a second group of codes; 0: one group is shorter."""
    down = np.cumsum(counts, 1)
    every = down[:, -1:]
    bits = _cost(down[:, :-1]) + _cost(every - down[:, :-1]) + 200  # the meta codes, and the heads of a group
    best = bits.argmin(1)
    return np.where(np.take_along_axis(bits, best[:, None], 1)[:, 0] < _cost(every)[:, 0], best + 1, 0)


def encode_grey(images: list[np.ndarray]) -> list[bytes]:
    """Lossless WebP files of grey samples, `ROW` in a row and at most `SEGMENT` each, with the transforms, back-references, groups and codes that suit each."""
    k = len(images)
    forms = _forms(images)
    height = np.array([len(a) // ROW for a in images])
    size = np.array([len(f[1]) for f in forms])
    pack = np.array([f[2] for f in forms])
    width = ROW >> pack
    a, image = np.concatenate([f[1] for f in forms]).astype(np.int64), np.repeat(np.arange(k), size)
    begin = np.cumsum(size) - size
    start, length, d = _repeats(a, image, begin)
    turn = np.zeros(len(a) + 1, np.int8)
    turn[start] += 1
    turn[start + length] -= 1
    plain = np.flatnonzero(np.cumsum(turn[:-1], dtype=np.int8) == 0)
    own, of = image[plain], image[start]
    ls, lv, ln = _value_symbols(SEGMENT + 120)[:, length]
    ds, dv, dn = _value_symbols(SEGMENT + 120)[:, np.stack([_distance_codes(ROW >> p, SEGMENT) for p in range(4)])[pack[of], d]]
    bands = -(-SEGMENT // ROW >> BLOCK)
    own_band, of_band = (plain - begin[own]) // width[own] >> BLOCK, (start - begin[of]) // width[of] >> BLOCK
    counts = np.bincount(np.concatenate([(own * bands + own_band) * 280 + a[plain], (of * bands + of_band) * 280 + 256 + ls]), minlength=280 * bands * k).reshape(k, bands, 280)
    cut = np.where(width == ROW, _cuts(counts), 0)
    # groups: the first of all images, then the second of those that have one
    two = np.flatnonzero(cut)
    second = np.zeros(k, np.int64)
    second[two] = k + np.arange(len(two))
    group_of = np.append(np.arange(k), two)
    low = (np.arange(bands) < np.where(cut, cut, bands)[:, None])[:, :, None]
    n, codes = _huffman(np.concatenate([np.where(low, counts, 0).sum(1), np.where(low, 0, counts).sum(1)[two]]), LONGEST)
    own_group = np.where((cut[own] > 0) & (own_band >= cut[own]), second[own], own)
    group = np.where((cut[of] > 0) & (of_band >= cut[of]), second[of], of)
    counts = np.bincount(group * 40 + ds, minlength=40 * len(group_of)).reshape(-1, 40)
    many, one = np.flatnonzero((counts > 0).sum(1) > 1), np.flatnonzero((counts > 0).sum(1) < 2)
    fn, fc = np.zeros((2, len(group_of), 40), np.int64)
    fn[many], fc[many] = _huffman(counts[many], LONGEST)
    # (image, part of the file, place in it, value, bits)
    lead = [(i, 0, j, v, m) for i, (f, h, c) in enumerate(zip(forms, height.tolist(), cut.tolist())) for j, (v, m) in enumerate(_lead(f[0], h, f[3], c))]
    tokens = [tuple(np.array(lead, np.int64).T)]
    every = np.arange(len(group_of))
    part = 5 * (every >= k)
    alpha = np.array([255 if f[0] == GREY else 0 for f in forms])[group_of]
    simple = 0b101 | 0b101 << 11 | (0b101 | alpha << 3) << 22  # red, blue and alpha: one symbol of 8 bits each
    (v, m), (r, at, lengths, bits) = _put_lengths(n)
    tokens += [(group_of, part + 1, 0 * every, v, m), (group_of[r], part[r] + 2, at, lengths, bits), (group_of, part + 3, 0 * every, simple, np.full(len(every), 33))]
    tokens.append((group_of[one], part[one] + 4, 0 * one, 0b101 | counts[one].argmax(1) << 3, np.full(len(one), 11)))
    if len(many):
        (v, m), (r, at, lengths, bits) = _put_lengths(fn[many])
        tokens += [(group_of[many], part[many] + 4, 0 * many, v, m), (group_of[many][r], part[many][r] + 5, at, lengths, bits)]
    cv, cn, fv, fm = codes[group, 256 + ls], n[group, 256 + ls], fc[group, ds], fn[group, ds]
    tokens.append((own, np.full(len(own), 11), plain - begin[own], codes[own_group, a[plain]], n[own_group, a[plain]]))
    tokens.append((of, np.full(len(of), 11), start - begin[of], cv | lv << cn | fv << cn + ln | dv << cn + ln + fm, cn + ln + fm + dn))
    bits = sum(np.bincount(t[0], t[4], k) for t in tokens).astype(np.int64)
    tokens.append((np.arange(k), np.full(k, 12), np.zeros(k, np.int64), np.zeros(k, np.int64), -bits % 8))
    order = np.argsort(np.concatenate([t[0] << 20 | t[1] << 16 | t[2] for t in tokens]), kind="stable")
    v, m = (np.concatenate([t[c] for t in tokens])[order] for c in (3, 4))
    at = np.arange(int(m.sum()), dtype=np.int32) - np.repeat((np.cumsum(m) - m).astype(np.int32), m)
    packed = np.packbits((np.repeat(v, m) >> at & 1).astype(np.uint8), bitorder="little").tobytes()
    to = np.cumsum(-(-bits // 8)).tolist()
    return [container(packed[i:j]) for i, j in zip([0] + to, to)]


def store(payloads: list[bytes]) -> list[list[bytes]]:
    """Payloads (multiples of 64 bytes) as lists of grey images."""
    images, many = [], []
    for x in payloads:
        a = np.frombuffer(x, np.uint8)
        images += [a[i : i + SEGMENT] for i in range(0, len(a), SEGMENT)]
        many.append(-(-len(a) // SEGMENT))
    files = [f for i in range(0, len(images), TOGETHER) for f in encode_grey(images[i : i + TOGETHER])]
    at = np.cumsum([0] + many).tolist()
    return [files[i:j] for i, j in zip(at, at[1:])]


def load(media: list[list[bytes]]) -> list[np.ndarray]:
    """The payloads of some lists of images."""
    parts = [(p >> 8).astype(np.uint8) for p, _, _ in decode_many([x for files in media for x in files])]
    at = np.cumsum([0] + [len(files) for files in media]).tolist()
    return [np.concatenate(parts[i:j]) for i, j in zip(at, at[1:])]


def feature(samples: np.ndarray) -> str:
    """16 hex digits: which of 64 equal runs of samples are brighter than the mean, from the decoded samples."""
    m = samples.reshape(64, -1).sum(1, dtype=np.int64)
    return np.packbits(m * 64 > m.sum()).tobytes().hex()


def media_table(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes and the media (list of WebP files) of every document; a null text is empty."""

    def run(batches):
        for x in C.freed(batches):
            for at, texts in T.slices_of(x.column(1)):
                yield C.batch_of({"doc_id": x.column(0).slice(at, len(texts)), "n_bytes": pa.array([len(t.encode()) for t in texts], pa.int64()), "media": pa.array(store([payload(t) for t in texts]), pa.list_(pa.binary()))})

    C.ship(docs.sparkSession)
    docs = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    return docs.mapInArrow(run, "doc_id long, n_bytes long, media array<binary>")


def decoded(media: DataFrame, samples: bool = False) -> DataFrame:
    """Digests and the feature of what the media decode to and, if asked for, the samples."""

    def run(batches):
        for x in C.freed(batches):
            ids, n, col = x.column(0), x.column(1), x.column(2)
            for i in range(0, len(x), 2000):
                rows = []
                some = col.slice(i, 2000).to_pylist()
                for files, a in zip(some, load(some)):
                    b = a.tobytes()
                    rows.append((len(b), hashlib.sha256(b).hexdigest(), zlib.crc32(b[-64:]), sum(map(len, files)), hashlib.sha256(b"".join(files)).hexdigest(), feature(a), b))
                cols = list(zip(*rows))
                names = (("payload_bytes", pa.int64()), ("payload_sha256", pa.string()), ("tail_crc32", pa.int64()), ("media_bytes", pa.int64()), ("media_sha256", pa.string()), ("feature", pa.string()), ("samples", pa.binary()))
                yield C.batch_of({"doc_id": ids.slice(i, len(rows)), "n_bytes": n.slice(i, len(rows))} | {k: pa.array(v, t) for (k, t), v in list(zip(names, cols))[: 6 + samples]})

    schema = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
    return media.mapInArrow(run, schema + ", samples binary" * samples)
