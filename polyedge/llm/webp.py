"""Media columns: lossless WebP images written and read in numpy.

The reader takes any lossless file: prefix codes with several groups, back-references, the colour
cache, and the predictor, cross-colour, subtract-green and palette transforms, also stacked.  Where
a picture has one group of codes and no cache, a code means the same at every bit, so the symbols and
lengths at all bit positions are looked up at once, the chain of those that are read is followed, and
only back-references are copied one by one; other pictures are read symbol by symbol.

The writer stores a byte payload as grey pixels, a byte each: with the palette transform where at most
16 values occur (several pixels then share one), else with subtract-green, which leaves one channel.
Repeated passages become back-references, found by sorted hashes of six bytes, and the rest has prefix
codes fitted to its counts.  A colour cache gains nothing where a pixel is one symbol, and the
spatial transforms are not tried on text, so ``store_bytes`` writes neither; ``encode_image`` writes all.

Defined results: a payload is padded with bytes 255 to a positive multiple of 576 (a row), so a null
or empty text is one row of white pixels; one beyond 1,024 rows continues in further files, one behind
the other.  Equal texts give equal files.  A broken file raises ValueError.
"""

from __future__ import annotations

import hashlib
import heapq
import struct
import zlib
from collections import Counter
from collections.abc import Sequence
from functools import cache, cached_property, partial
from itertools import chain

import numpy as np
from pyspark.sql import DataFrame, functions as F, types as T

from polyedge.llm import common

UNIT, WIDTH, MOST_ROWS = 576, 576, 1024
# fixed values of the format: order of code length codes; near distances as (columns left, rows up)
LENGTH_ORDER = [17, 18, 0, 1, 2, 3, 4, 5, 16, 6, 7, 8, 9, 10, 11, 12, 13, 14, 15]
NEAR = [
    (0, 1), (1, 0), (1, 1), (-1, 1), (0, 2), (2, 0), (1, 2), (-1, 2), (2, 1), (-2, 1), (2, 2), (-2, 2), (0, 3), (3, 0), (1, 3), (-1, 3),
    (3, 1), (-3, 1), (2, 3), (-2, 3), (3, 2), (-3, 2), (0, 4), (4, 0), (1, 4), (-1, 4), (4, 1), (-4, 1), (3, 3), (-3, 3), (2, 4), (-2, 4),
    (4, 2), (-4, 2), (0, 5), (3, 4), (-3, 4), (4, 3), (-4, 3), (5, 0), (1, 5), (-1, 5), (5, 1), (-5, 1), (2, 5), (-2, 5), (5, 2), (-5, 2),
    (4, 4), (-4, 4), (3, 5), (-3, 5), (5, 3), (-5, 3), (0, 6), (6, 0), (1, 6), (-1, 6), (6, 1), (-6, 1), (2, 6), (-2, 6), (6, 2), (-6, 2),
    (4, 5), (-4, 5), (5, 4), (-5, 4), (3, 6), (-3, 6), (6, 3), (-6, 3), (0, 7), (7, 0), (1, 7), (-1, 7), (5, 5), (-5, 5), (7, 1), (-7, 1),
    (4, 6), (-4, 6), (6, 4), (-6, 4), (2, 7), (-2, 7), (7, 2), (-7, 2), (3, 7), (-3, 7), (7, 3), (-7, 3), (5, 6), (-5, 6), (6, 5), (-6, 5),
    (8, 0), (4, 7), (-4, 7), (7, 4), (-7, 4), (8, 1), (8, 2), (6, 6), (-6, 6), (8, 3), (5, 7), (-5, 7), (7, 5), (-7, 5), (8, 4), (6, 7),
    (-6, 7), (7, 6), (-7, 6), (8, 5), (7, 7), (-7, 7), (8, 6), (8, 7),
]
PREDICTOR, CROSS_COLOUR, SUBTRACT_GREEN, PALETTE = range(4)
LITERALS, LENGTHS, DISTANCES = 256, 24, 40
SHARES = [1 << (15 - n) for n in range(16)]  # of all values of 15 bits, those that begin with a code of n bits
BLACK = 0xFF000000
CACHE_FACTOR = 0x1E35A7BD


# ---------------------------------------------------------------- bits and prefix codes


class BitReader:
    def __init__(self, data: bytes):
        self.data, self.at = data, 0

    def peek(self, n: int) -> int:
        i = self.at >> 3
        return int.from_bytes(self.data[i : i + 6], "little") >> (self.at & 7) & ((1 << n) - 1)

    def read(self, n: int) -> int:
        if self.at + n > 8 * len(self.data):
            raise ValueError("file ends early")
        v = self.peek(n)
        self.at += n
        return v


def canonical(lengths: Sequence[int]) -> dict[int, tuple[int, int]]:
    """Code and length of each symbol, codes written first bit first (so reversed)."""
    used = [(n, s) for s, n in enumerate(lengths) if n]
    if len(used) == 1:
        return {used[0][1]: (0, 0)}
    out, code, last = {}, 0, 0
    for n, s in sorted(used):
        code <<= n - last
        last = n
        out[s] = (turned(code, n), n)
        code += 1
    return out


@cache
def turned(code: int, n: int) -> int:
    """A code of ``n`` bits, at most 15, its bits in the other order."""
    return int(format(code, f"0{n}b")[::-1], 2)


@cache
def reversed_bits(n: int) -> np.ndarray:
    """Every number of ``n`` bits, its bits in the other order."""
    x, out = np.arange(1 << n), np.zeros(1 << n, np.int64)
    for _ in range(n):
        out = out << 1 | x & 1
        x = x >> 1
    return out


class PrefixCode:
    """Decoder of one code by a table over its longest length."""

    def __init__(self, lengths: Sequence[int]):
        self.given = lengths
        used = list(filter(None, lengths))
        if not used:
            raise ValueError("a prefix code without symbols")
        self.bits = max(used) if len(used) > 1 else 0
        if self.bits and sum(map(SHARES.__getitem__, used)) != SHARES[0]:
            raise ValueError("a prefix code is not complete")
        self._table: list[tuple[int, int]] | None = None

    @cached_property
    def lengths(self) -> dict[int, int]:
        """Length of each symbol, 0 of a lone one."""
        return {s: n if self.bits else 0 for s, n in enumerate(self.given) if n}

    def alone(self) -> int:
        """The one symbol of a code without bits."""
        return next(s for s, n in enumerate(self.given) if n)

    def tables(self) -> tuple[np.ndarray, np.ndarray]:
        """Symbol and length for each value of the next ``bits`` bits."""
        given = np.array(self.given, np.uint8)
        symbol = np.argsort(given, kind="stable")[-np.count_nonzero(given) :]
        length = given[symbol].astype(np.int64)
        times = 1 << (self.bits - length)
        order = reversed_bits(self.bits)
        return np.repeat(symbol, times)[order], np.repeat(length, times)[order]

    def table(self) -> list[tuple[int, int]]:
        """Symbol and length for each value of the next ``bits`` bits, as a list."""
        if self._table is None:
            self._table = [(0, 0)] * (1 << self.bits)
            for s, (code, n) in canonical(self.given).items():
                for high in range(1 << (self.bits - n)):
                    self._table[code | high << n] = (s, n)
        return self._table

    def symbol(self, r: BitReader) -> int:
        s, n = self.table()[r.peek(self.bits)]
        r.at += n
        return s


def read_code(r: BitReader, alphabet: int) -> PrefixCode:
    lengths = [0] * alphabet
    if r.read(1):
        two = r.read(1)
        lengths[r.read(8 if r.read(1) else 1)] = 1
        if two:
            lengths[r.read(8)] = 1
        return PrefixCode(lengths)
    of_lengths = [0] * 19
    n = 4 + r.read(4)
    for i in range(0, n, 10):
        three = r.read(3 * min(10, n - i))
        for k in LENGTH_ORDER[i : min(i + 10, n)]:
            of_lengths[k] = three & 7
            three >>= 3
    code = PrefixCode(of_lengths)
    left = 2 + r.read(2 + 2 * r.read(3)) if r.read(1) else alphabet
    table, mask = code.table(), (1 << code.bits) - 1
    at = r.at >> 3
    window = int.from_bytes(r.data[at : at + 2 * alphabet + 8], "little") >> (r.at & 7)
    used, s, last = 0, 0, 8
    while s < alphabet and left:
        left -= 1
        n, size = table[window & mask]
        window >>= size
        used += size
        if n < 16:
            lengths[s] = n
            s += 1
            last = n or last
        else:
            bits = (2, 3, 7)[n - 16]
            times = (3, 3, 11)[n - 16] + (window & ((1 << bits) - 1))
            window >>= bits
            used += bits
            if s + times > alphabet:
                raise ValueError("too many code lengths")
            if n == 16:
                lengths[s : s + times] = [last] * times
            s += times
    r.at += used
    if r.at > 8 * len(r.data):
        raise ValueError("file ends early")
    return PrefixCode(lengths)


def read_group(r: BitReader, cache_bits: int) -> list[PrefixCode]:
    sizes = [LITERALS + LENGTHS + (1 << cache_bits if cache_bits else 0), 256, 256, 256, DISTANCES]
    return [read_code(r, n) for n in sizes]


def read_value(r: BitReader, prefix: int) -> int:
    if prefix < 4:
        return prefix + 1
    extra = (prefix - 2) >> 1
    return ((2 + (prefix & 1)) << extra) + r.read(extra) + 1


# ---------------------------------------------------------------- reading pixels


EXTRA = np.array([0, 0, 0, 0, *[(p - 2) >> 1 for p in range(4, DISTANCES)]])  # extra bits of a prefix, and its least value
LEAST = np.array([1, 2, 3, 4, *[((2 + (p & 1)) << (p - 2 >> 1)) + 1 for p in range(4, DISTANCES)]])
SHIFTS = np.tile(np.arange(8, dtype=np.uint32), 1 << 13)


@cache
def _near(width: int) -> np.ndarray:
    return np.array([max(1, x + y * width) for x, y in NEAR], np.int64)


def _read_parallel(r: BitReader, codes: list[PrefixCode], width: int, n: int) -> np.ndarray:
    """Pixels of a picture of one group without a cache: all bit positions at once, then the chain."""
    first, ahead = r.at >> 3, r.at & 7
    raw = r.data[first:] + bytes(12)
    # the next 25 bits at each bit position
    view = np.repeat(np.ndarray(len(raw) - 3, "<u4", raw, 0, 1), 8)
    for at in range(0, len(view), len(SHIFTS)):
        view[at : at + len(SHIFTS)] >>= SHIFTS[: len(view) - at]
    end = 8 * (len(r.data) - first)  # bits of the file; positions up to 40 behind it can be looked at
    tables = [c.tables() if c.bits else (np.array([c.alone()]), np.zeros(1, np.int64)) for c in codes]
    masks = [np.uint32((1 << c.bits) - 1) for c in codes]

    def look(k: int, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        v = view[np.minimum(at, len(view) - 1)] & masks[k]
        return tables[k][0][v], tables[k][1][v]

    def value(prefix: np.ndarray, at: np.ndarray) -> np.ndarray:
        more = view[np.minimum(at, len(view) - 1)].astype(np.int64)
        return LEAST.take(prefix) + (more & ((1 << EXTRA.take(prefix)) - 1))

    symbol = (tables[0][0] << 4 | tables[0][1]).astype(np.uint16).take(view[: end + 1] & masks[0])  # and length
    after = np.arange(end + 1)
    after += symbol & 15
    copies = np.flatnonzero(symbol >= LITERALS << 4) if any(codes[0].given[LITERALS:]) else np.empty(0, np.int64)
    behind = after[copies]
    for k in (1, 2, 3):
        if codes[k].bits:
            after += tables[k][1].take(view.take(after, mode="clip") & masks[k])
    if len(copies):
        behind += EXTRA.take((symbol[copies] >> 4).astype(np.int64) - LITERALS)
        prefix, size = look(4, behind)
        after[copies] = behind + size + EXTRA.take(prefix)
    if not any(c.bits for c in codes[:4]):  # every pixel is the same and takes no bits
        argb = [int(t[0][0]) for t in tables[:4]]
        if argb[0] >= LITERALS:
            raise ValueError("a reference leaves the picture")
        return np.full(n, argb[3] << 24 | argb[1] << 16 | argb[0] << 8 | argb[2], np.uint32)
    # eight symbols a step, then those between
    jumps = [np.minimum(after, end)]
    for _ in range(3):
        jumps.append(jumps[-1].take(jumps[-1]))
    far, steps, at = [], memoryview(jumps[3]), ahead
    while at < end:
        far.append(at)
        at = steps[at]
    read = np.array(far, np.int64)
    for jump in jumps[2::-1]:
        both = np.empty(2 * len(read), np.int64)
        both[::2] = read
        both[1::2] = jump.take(read)
        read = both
    read = read[read < end]
    kind = (symbol[read] >> 4).astype(np.int64)
    counts = np.ones(len(read), np.int64)
    on = np.flatnonzero(kind >= LITERALS)
    if len(on):
        at = read[on] + look(0, read[on])[1]
        counts[on] = value(kind[on] - LITERALS, at)
        at += EXTRA.take(kind[on] - LITERALS)
        prefix, size = look(4, at)
        distance = value(prefix, at + size)
        near = _near(width)
        distance = np.where(distance > len(NEAR), distance - len(NEAR), near[np.minimum(distance, len(NEAR)) - 1])
    ends = np.cumsum(counts)
    tokens = int(np.searchsorted(ends, n)) + 1
    if tokens > len(ends) or ends[tokens - 1] != n:
        raise ValueError("file ends early" if tokens > len(ends) else "a reference leaves the picture")
    r.at = 8 * first + int(after[read[tokens - 1]])
    if r.at > 8 * len(r.data):
        raise ValueError("file ends early")
    starts = ends - counts
    plain = np.flatnonzero(kind[:tokens] < LITERALS)
    on = on[on < tokens]
    if len(on) and (distance[: len(on)] > starts[on]).any():
        raise ValueError("a reference leaves the picture")
    parts = (starts[on].tolist(), counts[on].tolist(), distance[: len(on)].tolist()) if len(on) else ((), (), ())
    if not any(c.bits for c in codes[1:4]):  # a byte each, as the green channel alone varies
        green = np.zeros(n, np.uint8)
        green[starts[plain]] = kind[plain]
        filled = bytearray(green)
        for i, c, d in zip(*parts, strict=True):
            filled[i : i + c] = filled[i - d : i - d + c] if d >= c else (filled[i - d : i] * (c // d + 1))[:c]
        rest = int(tables[3][0][0]) << 24 | int(tables[1][0][0]) << 16 | int(tables[2][0][0])
        out = np.frombuffer(filled, np.uint8).astype(np.uint32)
        out <<= np.uint32(8)
        out |= np.uint32(rest)
        return out
    out = np.zeros(n, np.uint32)
    at, argb = read[plain], kind[plain] << 8
    at = at + look(0, at)[1]
    for k, shift in ((1, 16), (2, 0), (3, 24)):
        s, size = look(k, at) if codes[k].bits else (tables[k][0][0], 0)
        argb |= s << shift
        at = at + size
    out[starts[plain]] = argb
    for i, c, d in zip(*parts, strict=True):
        out[i : i + c] = out[i - d : i - d + c] if d >= c else np.resize(out[i - d : i], c)
    return out


def read_pixels(r: BitReader, width: int, height: int, main: bool) -> np.ndarray:
    """ARGB values of one entropy-coded picture."""
    cache_bits = r.read(4) if r.read(1) else 0
    if cache_bits > 11:
        raise ValueError("colour cache too large")
    group_of, tile_bits, tiles = None, 0, 0
    if main and r.read(1):
        tile_bits = r.read(3) + 2
        tiles = (width + (1 << tile_bits) - 1) >> tile_bits
        meta = read_pixels(r, tiles, (height + (1 << tile_bits) - 1) >> tile_bits, False)
        group_of = (meta >> 8 & 0xFFFF).astype(np.int64).tolist()
    groups = [read_group(r, cache_bits) for _ in range(1 + (max(group_of) if group_of else 0))]
    n = width * height
    if len(groups) == 1 and not cache_bits:
        return _read_parallel(r, groups[0], width, n)
    out = [0] * n
    cache = [0] * (1 << cache_bits)
    shift = 32 - cache_bits
    i = 0
    codes = groups[0]
    while i < n:
        if group_of is not None:
            codes = groups[group_of[(i // width >> tile_bits) * tiles + (i % width >> tile_bits)]]
        s = codes[0].symbol(r)
        if s < LITERALS:
            red = codes[1].symbol(r)
            blue = codes[2].symbol(r)
            out[i] = codes[3].symbol(r) << 24 | red << 16 | s << 8 | blue
            count = 1
        elif s < LITERALS + LENGTHS:
            count = read_value(r, s - LITERALS)
            d = read_value(r, codes[4].symbol(r))
            if d > len(NEAR):
                d -= len(NEAR)
            else:
                d = max(1, NEAR[d - 1][0] + NEAR[d - 1][1] * width)
            if d > i or i + count > n:
                raise ValueError("a reference leaves the picture")
            for k in range(i, i + count):
                out[k] = out[k - d]
        else:
            out[i] = cache[s - LITERALS - LENGTHS]
            count = 1
        if cache_bits:
            for k in range(i, i + count):
                cache[(out[k] * CACHE_FACTOR & 0xFFFFFFFF) >> shift] = out[k]
        i += count
    if r.at > 8 * len(r.data):
        raise ValueError("file ends early")
    return np.array(out, np.uint32)


# ---------------------------------------------------------------- transforms


def split(argb: np.ndarray) -> np.ndarray:
    """Channels A, R, G, B as a last axis of int32."""
    return np.stack([argb >> np.uint32(s) & np.uint32(255) for s in (24, 16, 8, 0)], -1).astype(np.int32)


def join(c: np.ndarray) -> np.ndarray:
    c = (c & 255).astype(np.uint32)
    return c[..., 0] << 24 | c[..., 1] << 16 | c[..., 2] << 8 | c[..., 3]


def predict(mode: int, left: np.ndarray, top: np.ndarray, top_left: np.ndarray, top_right: np.ndarray) -> np.ndarray:
    def mean(a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return (a + b) >> 1

    match mode:
        case 0 | 14 | 15:
            return np.array([255, 0, 0, 0])
        case 1:
            return left
        case 2:
            return top
        case 3:
            return top_right
        case 4:
            return top_left
        case 5:
            return mean(mean(left, top_right), top)
        case 6:
            return mean(left, top_left)
        case 7:
            return mean(left, top)
        case 8:
            return mean(top_left, top)
        case 9:
            return mean(top, top_right)
        case 10:
            return mean(mean(left, top_left), mean(top, top_right))
        case 11:
            return left if np.abs(top - top_left).sum() < np.abs(left - top_left).sum() else top
        case 12:
            return np.clip(left + top - top_left, 0, 255)
        case _:
            a = mean(left, top)
            return np.clip(a + np.trunc((a - top_left) / 2).astype(np.int32), 0, 255)


def _predictions(x: np.ndarray, modes: np.ndarray, bits: int, residual: bool) -> np.ndarray:
    """Invert the predictor over channels, or with ``residual`` apply it."""
    h, w, _ = x.shape
    out = x.copy()
    seen = x if residual else out
    for y in range(h):
        for c in range(w):
            if y == 0:
                p = np.array([255, 0, 0, 0]) if c == 0 else seen[0, c - 1]
            elif c == 0:
                p = seen[y - 1, 0]
            else:
                right = seen[y - 1, c + 1] if c + 1 < w else seen[y, 0]
                p = predict(int(modes[y >> bits, c >> bits]), seen[y, c - 1], seen[y - 1, c], seen[y - 1, c - 1], right)
            out[y, c] = (x[y, c] - p if residual else x[y, c] + p) & 255
    return out


def _signed(x: np.ndarray) -> np.ndarray:
    return (x & 255 ^ 128) - 128


def _cross(x: np.ndarray, elements: np.ndarray, bits: int, sign: int) -> np.ndarray:
    h, w, _ = x.shape
    e = _signed(split(elements)[np.arange(h)[:, None] >> bits, np.arange(w) >> bits])
    red_blue, green_blue, green_red = e[..., 1], e[..., 2], e[..., 3]
    g = _signed(x[..., 2])
    out = x.copy()
    out[..., 1] = (x[..., 1] + sign * (green_red * g >> 5)) & 255
    true_red = out[..., 1] if sign > 0 else x[..., 1]
    out[..., 3] = (x[..., 3] + sign * ((green_blue * g >> 5) + (red_blue * _signed(true_red) >> 5))) & 255
    return out


def _bundle_bits(colours: int) -> int:
    return 3 if colours <= 2 else 2 if colours <= 4 else 1 if colours <= 16 else 0


def decode_image(data: bytes) -> np.ndarray:
    """ARGB pixel array (height, width) of one file."""
    if data[:4] != b"RIFF" or data[8:16] != b"WEBPVP8L" or data[20] != 0x2F:
        raise ValueError("not a lossless file")
    r = BitReader(data[21 : 20 + struct.unpack("<I", data[16:20])[0]])
    width, height = r.read(14) + 1, r.read(14) + 1
    r.read(1)
    if r.read(3):
        raise ValueError("unknown version")
    steps: list[tuple] = []
    w = width
    while r.read(1):
        kind = r.read(2)
        if kind in (PREDICTOR, CROSS_COLOUR):
            bits = r.read(3) + 2
            tw, th = (w + (1 << bits) - 1) >> bits, (height + (1 << bits) - 1) >> bits
            steps.append((kind, w, bits, read_pixels(r, tw, th, False).reshape(th, tw)))
        elif kind == PALETTE:
            n = r.read(8) + 1
            table = join(np.cumsum(split(read_pixels(r, n, 1, False)), axis=0))
            steps.append((kind, w, _bundle_bits(n), table))
            w = (w + (1 << _bundle_bits(n)) - 1) >> _bundle_bits(n)
        else:
            steps.append((kind, w, 0, None))
    argb = read_pixels(r, w, height, True).reshape(height, w)
    for kind, w, bits, extra in reversed(steps):
        if kind == SUBTRACT_GREEN:
            green = argb >> np.uint32(8) & np.uint32(255)
            argb = argb & np.uint32(0xFF00FF00) | (argb & np.uint32(0x00FF00FF)) + (green << np.uint32(16) | green) & np.uint32(0x00FF00FF)
        elif kind == PREDICTOR:
            argb = join(_predictions(split(argb), extra >> 8 & 15, bits, False))
        elif kind == CROSS_COLOUR:
            argb = join(_cross(split(argb), extra, bits, 1))
        else:
            index = argb >> np.uint32(8) & np.uint32(255)
            if bits:
                each = 8 >> bits
                index = (index[..., None] >> (np.arange(1 << bits, dtype=np.uint32) * np.uint32(each)) & np.uint32((1 << each) - 1)).reshape(height, -1)[:, :w]
            table = np.zeros(256, np.uint32)
            table[: len(extra)] = extra
            argb = table[index]
    return argb


# ---------------------------------------------------------------- writing


class BitWriter:
    def __init__(self) -> None:
        self.value, self.n = 0, 0

    def put(self, v: int, n: int) -> None:
        self.value |= v << self.n
        self.n += n

    def bytes(self) -> bytes:
        return self.value.to_bytes((self.n + 7) // 8, "little")


def _container(bits: bytes) -> bytes:
    body = b"\x2f" + bits
    pad = len(body) & 1
    return b"RIFF" + struct.pack("<I", 12 + len(body) + pad) + b"WEBPVP8L" + struct.pack("<I", len(body)) + body + b"\0" * pad


def write_code(w: BitWriter, lengths: list[int]) -> None:
    """Write the code lengths."""
    used = [s for s, n in enumerate(lengths) if n]
    if len(used) <= 1 and (not used or used[0] < 256):
        s = used[0] if used else 0
        w.put(1, 1)
        w.put(0, 1)
        w.put(s > 1, 1)
        w.put(s, 8 if s > 1 else 1)
        return
    parts: list[tuple[int, int, int]] = []  # length or run symbol, extra bits, their value
    at = 0
    for s in used:
        run, at = s - at, s + 1  # zeros before the symbol
        while run >= 3:
            n = min(run, 138)
            parts.append((18, 7, n - 11) if n >= 11 else (17, 3, n - 3))
            run -= n
        parts += [(0, 0, 0)] * run
        parts.append((lengths[s], 0, 0))
    counts = Counter([p[0] for p in parts])
    of = _huffman(counts, 19, 7)
    codes = canonical(of)
    last = max(LENGTH_ORDER.index(k) for k, n in enumerate(of) if n)
    w.put(0, 1)
    w.put(max(4, last + 1) - 4, 4)
    for k in LENGTH_ORDER[: max(4, last + 1)]:
        w.put(of[k], 3)
    if len(parts) >= 2:
        w.put(1, 1)
        size = max(2, (len(parts) - 2).bit_length() + 1) // 2 * 2
        w.put((size - 2) // 2, 3)
        w.put(len(parts) - 2, size)
    else:
        w.put(0, 1)
        parts += [(0, 0, 0)] * (len(lengths) - 1 - used[-1]) if 0 in codes else [(parts[0][0], 0, 0)] * (len(lengths) - 1)
    value, size = 0, 0
    for k, extra, v in parts:
        code, n = codes[k]
        value |= (code | v << n) << size
        size += n + extra
    w.put(value, size)


def _depths(counts: Sequence[int]) -> list[int]:
    """Code lengths of least total for two counts or more."""
    n = len(counts)
    heap = [c << 16 | i for i, c in enumerate(counts)]  # count, then place
    heapq.heapify(heap)
    parent = [0] * (2 * n - 1)
    for node in range(n, 2 * n - 1):
        a = heapq.heappop(heap)
        b = heap[0]
        parent[a & 0xFFFF] = parent[b & 0xFFFF] = node
        heapq.heapreplace(heap, (a >> 16) + (b >> 16) << 16 | node)
    depth = [0] * (2 * n - 1)
    for i in range(2 * n - 3, -1, -1):
        depth[i] = depth[parent[i]] + 1
    return depth[:n]


def _huffman(counts: dict[int, int], alphabet: int, most: int = 15) -> list[int]:
    """Code lengths of at most ``most`` bits; counts are flattened until they fit."""
    lengths = [0] * alphabet
    used = sorted(counts)
    if len(used) == 1:
        lengths[used[0]] = 1
        return lengths
    c = [counts[s] for s in used]
    while max(found := _depths(c)) > most:
        c = [(x + 1) // 2 for x in c]
    for s, n in zip(used, found, strict=True):
        lengths[s] = n
    return lengths


SPREAD = np.uint64(CACHE_FACTOR * 0x9E3779B1)
LEAST_COPY, MOST_COPY, MOST_DISTANCE = 6, 4096, (1 << 20) - 120


def _copies(x: np.ndarray) -> list[tuple[int, int, int]]:
    """(place, length, distance) of back-references, from the left: each run of places whose last
    occurrence of the same six bytes lies at one distance."""
    n = len(x) - LEAST_COPY + 1
    if n < 2:
        return []
    two = x[:-1].astype(np.uint64) << np.uint64(8) | x[1:]
    key = (two[:n] << np.uint64(16) | two[2 : n + 2]) << np.uint64(16) | two[4 : n + 4]
    place = np.uint64(24)
    order = np.sort((key * SPREAD >> place << place) | np.arange(n, dtype=np.uint64))
    at = (order & np.uint64((1 << 24) - 1)).astype(np.int64)
    same = np.flatnonzero(order[1:] >> place == order[:-1] >> place)
    here, there = at[same + 1], at[same]
    real = (key[here] == key[there]) & (here - there <= MOST_DISTANCE)
    distance = np.zeros(n + 1, np.int64)
    distance[here[real]] = (here - there)[real]
    edge = np.flatnonzero(distance[1:] != distance[:-1]) + 1
    begin = np.concatenate([[0], edge[:-1]]) if len(edge) else edge
    of = distance[begin]
    on = of > 0
    out, free = [], 0
    for a, b, d in zip(begin[on].tolist(), (edge[on] + (LEAST_COPY - 1)).tolist(), of[on].tolist(), strict=True):
        if a < free:
            a = free
        n = b - a
        while n >= LEAST_COPY:
            if n > MOST_COPY:
                n = MOST_COPY
            out.append((a, n, d))
            a = free = a + n
            n = b - a
    return out


def _prefixes(v: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``_prefix`` of many values."""
    low = v - 1
    high = np.frexp(np.maximum(low, 1).astype(np.float64))[1].astype(np.int64) - 1
    small = v <= 4
    extra = np.where(small, 0, high - 1)
    return np.where(small, low, 2 * high + (low >> np.maximum(high - 1, 0) & 1)), extra, low & ((1 << extra) - 1)


def _codes(symbols: np.ndarray, alphabet: int) -> tuple[list[int], np.ndarray, np.ndarray]:
    """Lengths of a fitted code and, for each symbol, its bits and their number (0 for a lone symbol)."""
    counts = np.bincount(symbols, minlength=alphabet)
    used = np.flatnonzero(counts)
    lengths = _huffman(dict(zip(used.tolist(), counts[used].tolist(), strict=True)), alphabet) if len(used) else [1] + [0] * (alphabet - 1)
    bits, size = np.zeros(alphabet, np.int64), np.array(lengths)
    if len(used) < 2:
        return lengths, bits, np.zeros(alphabet, np.int64)
    order = used[np.argsort(size[used], kind="stable")]
    longest = int(size.max())
    times = 1 << (longest - size[order])
    bits[order] = reversed_bits(longest)[np.cumsum(times) - times]
    return lengths, bits, size


def _join_bits(w: BitWriter, value: np.ndarray, size: np.ndarray) -> bytes:
    """Bytes of what was written, then of the values (up to 63 bits), first bit first."""
    at = w.n + np.cumsum(size) - size
    total = int(at[-1] + size[-1]) if len(at) else w.n
    words = np.zeros(total // 64 + 2, np.uint64)
    if not size.all():
        on = np.flatnonzero(size)
        value, at, size = value[on], at[on], size[on]
    if len(size):
        value = value.view(np.uint64)
        word, low = at >> 6, at & 63
        shift = low.view(np.uint64)
        first = np.concatenate([[0], np.flatnonzero(word[1:] != word[:-1]) + 1])
        words[word[first]] = np.bitwise_or.reduceat(value << shift, first)
        over = np.flatnonzero(low + size > 64)
        words[word[over] + 1] |= value[over] >> (np.uint64(64) - shift[over])
    head = np.frombuffer(w.value.to_bytes((w.n + 63) // 64 * 8, "little"), np.uint64)
    words[: len(head)] |= head
    return words.tobytes()[: (total + 7) // 8]


def _write_channel(w: BitWriter, x: np.ndarray) -> bytes:
    """All bytes of a file whose main picture, in which the green channel alone varies, comes next."""
    w.put(0, 2)  # no cache, one group
    copies = _copies(x)
    places, sizes, ways = np.fromiter(chain.from_iterable(copies), np.int64, 3 * len(copies)).reshape(-1, 3).T
    covered = np.zeros(len(x) + 1, np.int8)
    covered[places] = 1
    covered[places + sizes] -= 1
    begins = np.cumsum(covered[:-1], dtype=np.int8) == 0  # of a literal or a copy
    begins[places] = True
    (symbol, far), (lx, dx), (lv, dv) = (np.split(v, 2) for v in _prefixes(np.concatenate([sizes, ways + len(NEAR)])))
    green = x.astype(np.int64)
    green[places] = symbol + LITERALS
    green = green[begins]
    lengths, bits, size = _codes(green, LITERALS + LENGTHS)
    far_lengths, far_bits, far_size = _codes(far, DISTANCES)
    write_code(w, lengths)
    for only, n in ((0, 1), (0, 1), (255, 8)):  # red, blue and alpha have one symbol
        w.put(1 | (n == 8) << 2 | only << 3, 3 + n)
    write_code(w, far_lengths)
    value, count = bits.take(green), size.take(green)
    if len(places):
        at = np.flatnonzero(green >= LITERALS)
        more, n = lv, lx
        for v, many in ((far_bits[far], far_size[far]), (dv, dx)):
            more = more | v << n
            n = n + many
        value[at] |= more << count[at]
        count[at] += n
    return _join_bits(w, value, count)


def store_bytes(payload: bytes) -> bytes:
    """Files that hold ``payload`` (a multiple of 576 bytes), three bytes a pixel."""
    if not payload or len(payload) % UNIT:
        raise ValueError(f"a payload is a positive multiple of {UNIT} bytes")
    most = MOST_ROWS * UNIT
    return b"".join(_store_one(payload[i : i + most]) for i in range(0, len(payload), most))


def _store_one(payload: bytes) -> bytes:
    x = np.frombuffer(payload, np.uint8)
    rows = len(x) // WIDTH
    w = BitWriter()
    w.put(WIDTH - 1, 14)
    w.put(rows - 1, 14)
    w.put(0, 1 + 3)  # no alpha, version
    w.put(1, 1)
    used = np.flatnonzero(np.bincount(x, minlength=256))
    if len(used) <= 16:
        w.put(PALETTE, 2)
        w.put(len(used) - 1, 8)
        write_pixels(w, join(np.diff(split(np.uint32(BLACK) | used.astype(np.uint32) * np.uint32(0x010101)), axis=0, prepend=0)).reshape(1, -1), False)
        bits = _bundle_bits(len(used))
        index = np.searchsorted(used, x).reshape(rows, -1, 1 << bits)
        x = (index << (np.arange(1 << bits) * (8 >> bits))).sum(-1).astype(np.uint8).ravel()
    else:
        w.put(SUBTRACT_GREEN, 2)
    w.put(0, 1)
    return _container(_write_channel(w, x))


def read_bytes(media: bytes) -> bytes:
    """The payload of ``store_bytes``, through the reader."""
    out, at = [], 0
    while at < len(media):
        size = 8 + struct.unpack("<I", media[at + 4 : at + 8])[0]
        out.append(decode_image(media[at : at + size]).ravel().astype(np.uint8).tobytes())
        at += size
    return b"".join(out)


def _prefix(value: int) -> tuple[int, int, int]:
    """Prefix symbol, number of extra bits and their value."""
    if value <= 4:
        return value - 1, 0, 0
    v = value - 1
    high = v.bit_length() - 1
    second = v >> (high - 1) & 1
    return 2 * high + second, high - 1, v & ((1 << (high - 1)) - 1)


def write_pixels(w: BitWriter, argb: np.ndarray, main: bool, cache_bits: int = 0, references: bool = False, near: bool = True) -> None:
    flat = argb.ravel().tolist()
    width = argb.shape[1]
    tokens: list[tuple] = []
    cache = [None] * (1 << cache_bits)
    last: dict[tuple, int] = {}
    i = 0
    near_code = {x + y * width: k + 1 for k, (x, y) in reversed(list(enumerate(NEAR))) if x + y * width >= 1} if near else {}
    while i < len(flat):
        count = 1
        key = tuple(flat[i : i + 3])
        j = last.get(key) if references else None
        if j is not None:
            while count < 4096 and i + count < len(flat) and flat[j + count] == flat[i + count]:
                count += 1
        if j is not None and count >= 3:
            tokens.append(("copy", count, near_code.get(i - j, i - j + len(NEAR))))
        else:
            count = 1
            slot = (flat[i] * CACHE_FACTOR & 0xFFFFFFFF) >> (32 - cache_bits)
            tokens.append(("cache", slot) if cache_bits and cache[slot] == flat[i] else ("pixel", flat[i]))
        for k in range(i, i + count):
            last[tuple(flat[k : k + 3])] = k
            if cache_bits:
                cache[(flat[k] * CACHE_FACTOR & 0xFFFFFFFF) >> (32 - cache_bits)] = flat[k]
        i += count
    symbols: list[list[tuple[int, int, int, int]]] = []  # code number, symbol, extra bits, their value
    for t in tokens:
        if t[0] == "pixel":
            p = t[1]
            symbols.append([(0, p >> 8 & 255, 0, 0), (1, p >> 16 & 255, 0, 0), (2, p & 255, 0, 0), (3, p >> 24, 0, 0)])
        elif t[0] == "cache":
            symbols.append([(0, LITERALS + LENGTHS + t[1], 0, 0)])
        else:
            a, b = _prefix(t[1]), _prefix(t[2])
            symbols.append([(0, LITERALS + a[0], *a[1:]), (4, b[0], *b[1:])])
    w.put(cache_bits > 0, 1)
    if cache_bits:
        w.put(cache_bits, 4)
    if main:
        w.put(0, 1)
    sizes = [LITERALS + LENGTHS + (1 << cache_bits if cache_bits else 0), 256, 256, 256, DISTANCES]
    codes = []
    for k, n in enumerate(sizes):
        counts = Counter(s[1] for group in symbols for s in group if s[0] == k)
        lengths = _huffman(counts, n) if counts else [1] + [0] * (n - 1)
        write_code(w, lengths)
        codes.append(canonical(lengths))
    for group in symbols:
        for k, s, n, v in group:
            w.put(*codes[k][s])
            w.put(v, n)


def encode_image(argb: np.ndarray, transforms: Sequence[tuple] = (), cache_bits: int = 0, references: bool = False) -> bytes:
    """Write an ARGB array (height, width) with transforms, colour cache and back-references.

    Transforms: ("predictor", bits, modes), ("cross", bits, elements), ("green",), ("palette",).
    """
    w = BitWriter()
    h, width = argb.shape
    w.put(width - 1, 14)
    w.put(h - 1, 14)
    w.put(1, 1)
    w.put(0, 3)
    x = argb.astype(np.uint32)
    for t in transforms:
        w.put(1, 1)
        if t[0] == "green":
            w.put(SUBTRACT_GREEN, 2)
            c = split(x)
            c[..., 1] -= c[..., 2]
            c[..., 3] -= c[..., 2]
            x = join(c)
        elif t[0] == "palette":
            table, index = np.unique(x, return_inverse=True)
            if len(table) > 256:
                raise ValueError("too many colours for a palette")
            w.put(PALETTE, 2)
            w.put(len(table) - 1, 8)
            c = split(table)
            write_pixels(w, join(np.diff(c, axis=0, prepend=0)).reshape(1, -1), False)
            bits = _bundle_bits(len(table))
            index = np.pad(index.reshape(x.shape), ((0, 0), (0, -x.shape[1] % (1 << bits)))).reshape(h, -1, 1 << bits)
            green = (index << (np.arange(1 << bits) * (8 >> bits))).sum(-1)
            x = np.uint32(BLACK) | (green.astype(np.uint32) << 8)
        else:
            bits, extra = t[1], t[2]
            w.put(PREDICTOR if t[0] == "predictor" else CROSS_COLOUR, 2)
            w.put(bits - 2, 3)
            if t[0] == "predictor":
                write_pixels(w, np.uint32(BLACK) | (extra.astype(np.uint32) << 8), False)
                x = join(_predictions(split(x), extra, bits, True))
            else:
                write_pixels(w, extra, False)
                x = join(_cross(split(x), extra, bits, -1))
    w.put(0, 1)
    write_pixels(w, x, True, cache_bits, references)
    return _container(w.bytes())


# ---------------------------------------------------------------- columns


def pad(raw: bytes) -> bytes:
    return raw + b"\xff" * (UNIT if not raw else -len(raw) % UNIT)


def feature(pixels: bytes) -> str:
    """Size of the picture and mean, deviation and entropy of its samples."""
    share = np.bincount(np.frombuffer(pixels, np.uint8), minlength=256) / len(pixels)
    values = np.arange(256)
    mean = (share * values).sum()
    sd = np.sqrt((share * (values - mean) ** 2).sum())
    share = share[share > 0]
    return f"{WIDTH}x{len(pixels) // WIDTH} mean {mean:.4f} sd {sd:.4f} entropy {-(share * np.log2(share)).sum():.4f}"


def _stored(texts: list[str]) -> list[list]:
    common.keep_freed()
    raw = [t.encode("utf-8", "surrogatepass") for t in texts]
    return [[len(b) for b in raw], [store_bytes(pad(b)) for b in raw]]


def store_texts(docs: DataFrame, text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """Append ``n_bytes`` and ``media``, the text's bytes as lossless pictures."""
    return common.with_text_columns(docs, text_col, _stored, [("n_bytes", T.LongType()), ("media", T.BinaryType())], keep)


def _pixels(batches, n_keep: int, names: list[str]):
    import pyarrow as pa

    for b in batches:
        for at in range(0, b.num_rows, 64):
            p = b.slice(at, 64)
            got = [decode_image(m) if m is not None else None for m in p.column(n_keep).to_pylist()]
            cols = [
                pa.array([None if g is None else g.shape[1] for g in got], pa.int32()),
                pa.array([None if g is None else g.shape[0] for g in got], pa.int32()),
                pa.array([None if g is None else g.ravel().astype(np.int64) for g in got], pa.list_(pa.int64())),
            ]
            yield pa.RecordBatch.from_arrays([*p.columns[:n_keep], *cols], names=names)


def decode_pixels(images: DataFrame, media_col: str = "media") -> DataFrame:
    """Append ``width``, ``height`` and ``argb`` (array of pixels) of a column of single files."""
    common.ship(images.sparkSession)
    made = ("width", "height", "argb")
    kept = [c for c in images.columns if c.lower() not in made]
    rows = images.select(*[F.col(f"`{c}`") for c in kept], F.col(f"`{media_col}`").alias("__media"))
    schema = T.StructType([*rows.schema.fields[:-1], T.StructField("width", T.IntegerType()), T.StructField("height", T.IntegerType()), T.StructField("argb", T.ArrayType(T.LongType()))])
    return rows.mapInArrow(partial(_pixels, n_keep=len(kept), names=[*kept, *made]), schema)


def _digested(texts: list[str]) -> list[list]:
    common.keep_freed()
    cols: list[list] = [[] for _ in range(7)]
    for t in texts:
        raw = t.encode("utf-8", "surrogatepass")
        media = store_bytes(pad(raw))
        back = read_bytes(media)
        row = [len(raw), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-32:]), len(media), hashlib.sha256(media).hexdigest(), feature(back)]
        for c, v in zip(cols, row, strict=True):
            c.append(v)
    return cols


def digest(docs: DataFrame) -> DataFrame:
    """Sizes and digests of the stored form and of the payload read back from it, and a feature."""
    fields = [("n_bytes", T.LongType()), ("payload_bytes", T.LongType()), ("payload_sha256", T.StringType()), ("tail_crc32", T.LongType()), ("media_bytes", T.LongType()), ("media_sha256", T.StringType()), ("feature", T.StringType())]
    return common.with_text_columns(docs, "text", _digested, fields, keep=["doc_id"])
