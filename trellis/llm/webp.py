"""Lossless WebP: a decoder to pixel arrays, and the encoder that fills the media column.

The decoder reads the whole lossless bit stream: prefix codes (simple and normal, with meta
prefix images), literals, back-references with their two-dimensional distance map, the colour
cache, and the four transforms (predictor, cross-colour, subtract-green, palette with packed
pixels), which it inverts in reverse order. Images of one group of codes with one channel that
varies, and predictors that look one way throughout, take a vectorised way. Pixel arrays can be
written beside the digests.

The encoder writes grey images whose samples are the payload. For each it chooses what seems
shortest: plain samples, differences to the sample on the left or above (predictor), or a palette
with packed pixels where there are few values; then what was there before becomes back-references;
tiny images also try the colour cache. `encode` writes any image with given transforms, cache,
back-references and groups of codes; cross-colour and groups of codes don't help grey samples.

Nulls: a null text is an empty payload, padded like any other. The stored bytes depend on the
payload alone, so equal texts and repeated rows give equal values; of choices of equal length (a
tie) the first named counts. Texts have any length: a payload too tall for one image becomes
several, one after the other. An empty table stays empty.
"""

from __future__ import annotations

import hashlib
import heapq
import math
import struct
import zlib
from dataclasses import dataclass, field
from functools import lru_cache
from itertools import groupby

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_rows

# Fixed values of the format.
SIGNATURE = 0x2F
CODE_LENGTH_ORDER = (17, 18, 0, 1, 2, 3, 4, 5, 16, 6, 7, 8, 9, 10, 11, 12, 13, 14, 15)
PREDICTOR, CROSS_COLOR, SUBTRACT_GREEN, PALETTE = 0, 1, 2, 3
LITERALS, LENGTHS, DISTANCES = 256, 24, 40
CACHE_HASH = 0x1E35A7BD
BLACK = 0xFF000000
# (columns left, rows up) of the 120 short distance codes.
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
#: Tallest image.
SIDE = 1 << 14
#: Columns of a stored payload.
COLUMNS = 64


# --- prefix codes ---------------------------------------------------------------------------------


def code_lengths(counts: list[int], most: int = 15) -> list[int]:
    """Lengths of an optimal prefix code; counts are flattened until none is longer than `most`."""
    used = [k for k, n in enumerate(counts) if n]
    out = [0] * len(counts)
    if len(used) < 2:
        return out
    floor = 1
    while True:
        heap = [(max(counts[k], floor), k, (k,)) for k in used]
        heapq.heapify(heap)
        depth = dict.fromkeys(used, 0)
        while len(heap) > 1:
            a, ka, sa = heapq.heappop(heap)
            b, kb, sb = heapq.heappop(heap)
            for s in sa + sb:
                depth[s] += 1
            heapq.heappush(heap, (a + b, min(ka, kb), sa + sb))
        if max(depth.values()) <= most:
            for k, n in depth.items():
                out[k] = n
            return out
        floor = floor * 2 + max(counts) // (1 << most)


#: Numbers of 15 bits, their bits reversed.
REVERSED = [int(f"{k:015b}"[::-1], 2) for k in range(1 << 15)]


def canonical(lengths: list[int]) -> list[int]:
    """Codes of the lengths, their bits reversed as the stream has them."""
    top = max(lengths, default=0)
    count = [0] * (top + 2)
    for n in lengths:
        count[n] += n > 0
    code, first = 0, [0] * (top + 2)
    for n in range(1, top + 1):
        code = (code + count[n - 1] * (n > 1)) << 1
        first[n] = code
    out = [0] * len(lengths)
    for k, n in enumerate(lengths):
        if n:
            out[k] = REVERSED[first[n]] >> (15 - n)
            first[n] += 1
    return out


class Code:
    """A prefix code as look-up tables over the next bits; one symbol alone takes no bits."""

    def __init__(self, lengths: list[int], only: int | None = None):
        used = [k for k, n in enumerate(lengths) if n]
        if only is None and len(used) == 1:
            only = used[0]
        if only is None and not used:
            only = 0
        self.only, self.lengths = only, lengths
        if only is None:
            self.bits = max(lengths)
            if sum(1 << (self.bits - n) for n in lengths if n) != 1 << self.bits:
                raise ValueError("not a complete prefix code")
            self.size, self.symbol = np.zeros(1 << self.bits, np.uint8), np.zeros(1 << self.bits, np.int32)
            codes = canonical(lengths)
            for k in used:
                n, c = lengths[k], codes[k]
                self.size[c :: 1 << n] = n
                self.symbol[c :: 1 << n] = k
            self.table: list[tuple[int, int]] | None = None

    def read(self, bits: Bits) -> int:
        if self.only is not None:
            return self.only
        if self.table is None:
            self.table = list(zip(self.size.tolist(), self.symbol.tolist(), strict=True))
        n, symbol = self.table[bits.peek(self.bits)]
        bits.at += n
        return symbol


class Bits:
    """Reads a stream of bits, least significant first."""

    def __init__(self, data: bytes):
        self.data, self.at = data + bytes(8), 0

    def peek(self, n: int) -> int:
        at = self.at >> 3
        if at > len(self.data):
            raise ValueError("the stream ends early")
        return (int.from_bytes(self.data[at : at + 8], "little") >> (self.at & 7)) & ((1 << n) - 1)

    def take(self, n: int) -> int:
        value = self.peek(n)
        self.at += n
        return value


class Writer:
    """Writes bits, least significant first, into one growing number; for headers and small images."""

    def __init__(self):
        self.value, self.n = 0, 0

    def put(self, value: int, n: int) -> None:
        self.value |= value << self.n
        self.n += n

    def bytes(self) -> bytes:
        return self.value.to_bytes((self.n + 7) // 8, "little")


def read_code(bits: Bits, alphabet: int) -> Code:
    if bits.take(1):
        two = bits.take(1)
        first = bits.take(8 if bits.take(1) else 1)
        if not two:
            return Code([], only=first)
        lengths = [0] * alphabet
        lengths[first] = lengths[bits.take(8)] = 1
        return Code(lengths)
    sizes = [0] * 19
    for k in CODE_LENGTH_ORDER[: bits.take(4) + 4]:
        sizes[k] = bits.take(3)
    left = 2 + bits.take(2 + 2 * bits.take(3)) if bits.take(1) else alphabet
    code, lengths, before = Code(sizes), [], 8
    while len(lengths) < alphabet and left:
        left -= 1
        s = code.read(bits)
        if s < 16:
            lengths.append(s)
            before = s or before
        else:
            lengths += [before if s == 16 else 0] * ((3, 3, 11)[s - 16] + bits.take((2, 3, 7)[s - 16]))
    if len(lengths) > alphabet:
        raise ValueError("code lengths overrun the alphabet")
    return Code(lengths + [0] * (alphabet - len(lengths)))


#: A complete code for code lengths: four bits up to 12, five above and for runs.
_META_SIZES = [4] * 13 + [5] * 6
_META = list(zip(canonical(_META_SIZES), _META_SIZES, strict=True))


def write_code(w: Writer, lengths: list[int], used: list[int]) -> None:
    """The code of these lengths; `used` symbols, when one or two, take the simple form."""
    if len(used) < 2:
        first = used[0] if used else 0
        if first < 256:
            w.put(0b001 | (first > 1) << 2, 3)
            w.put(first, 8 if first > 1 else 1)
            return
        lengths = [0] * len(lengths)
        lengths[first] = 1  # a single symbol beyond the simple form's reach
    w.put(0, 1)
    w.put(15, 4)
    for k in CODE_LENGTH_ORDER:
        w.put(_META_SIZES[k], 3)
    w.put(0, 1)
    for n, run in groupby(lengths):
        left = len(list(run))
        while n == 0 and left >= 3:
            k = min(left, 138)
            symbol, base, extra = (18, 11, 7) if k >= 11 else (17, 3, 3)
            w.put(*_META[symbol])
            w.put(k - base, extra)
            left -= k
        for _ in range(left):
            w.put(*_META[n])


# --- decoding -------------------------------------------------------------------------------------


def spread(prefix: int, bits: Bits) -> int:
    """Value of a length or distance prefix and its extra bits."""
    if prefix < 4:
        return prefix + 1
    extra = (prefix - 2) >> 1
    return ((2 + (prefix & 1)) << extra) + bits.take(extra) + 1


def blocks(n: int, bits: int) -> int:
    return (n + (1 << bits) - 1) >> bits


def read_pixels(bits: Bits, width: int, height: int, main: bool) -> np.ndarray:
    """An entropy-coded image as height x width of ARGB."""
    cache_bits = bits.take(4) if bits.take(1) else 0
    if cache_bits > 11:
        raise ValueError("bad colour cache")
    groups, group_bits, meta = 1, 0, None
    if main and bits.take(1):
        group_bits = bits.take(3) + 2
        meta = (read_pixels(bits, blocks(width, group_bits), blocks(height, group_bits), False) >> 8) & 0xFFFF
        groups = int(meta.max()) + 1
    alphabets = (LITERALS + LENGTHS + (1 << cache_bits if cache_bits else 0), 256, 256, 256, DISTANCES)
    codes = [[read_code(bits, n) for n in alphabets] for _ in range(groups)]
    total = width * height
    if groups == 1 and not cache_bits and all(c.only is not None for c in codes[0][1:4]) and codes[0][0].only is None:
        red, blue, alpha = (c.only for c in codes[0][1:4])
        fast = one_channel(bits, codes[0][0], codes[0][4], total, width)
        return (fast.astype(np.uint32) << np.uint32(8) | np.uint32(alpha << 24 | red << 16 | blue)).reshape(height, width)
    out: list[int] = []
    cache = [0] * (1 << cache_bits)
    while len(out) < total:
        at = len(out)
        g = codes[int(meta[at // width >> group_bits, at % width >> group_bits]) if meta is not None else 0]
        s = g[0].read(bits)
        if s < LITERALS:
            red, blue, alpha = g[1].read(bits), g[2].read(bits), g[3].read(bits)
            new = [alpha << 24 | red << 16 | s << 8 | blue]
        elif s < LITERALS + LENGTHS:
            n = spread(s - LITERALS, bits)
            d = distance(spread(g[4].read(bits), bits), width)
            if d > at or at + n > total:
                raise ValueError("a back-reference leaves the image")
            new = out[at - d : at - d + n] if d >= n else (out[at - d :] * (n // d + 1))[:n]
        else:
            new = [cache[s - LITERALS - LENGTHS]]
        out += new
        if cache_bits:
            for c in new:
                cache[(c * CACHE_HASH & 0xFFFFFFFF) >> (32 - cache_bits)] = c
    return np.array(out, np.uint32).reshape(height, width)


def distance(code: int, width: int) -> int:
    """Pixels back, of a distance code: the first of them mean places nearby."""
    return max(1, NEAR[code - 1][0] + NEAR[code - 1][1] * width) if code <= len(NEAR) else code - len(NEAR)


def one_channel(bits: Bits, code: Code, far: Code, total: int, width: int) -> np.ndarray:
    """The varying channel of an image: literals are only stepped over, and then looked up all at once."""
    begin = bits.at >> 3
    raw = np.frombuffer(bits.data, np.uint8, len(bits.data) - begin, begin).astype(np.uint32)
    word = raw[:-2] | raw[1:-1] << np.uint32(8) | raw[2:] << np.uint32(16)
    window = ((word[:, None] >> np.arange(8, dtype=np.uint32)) & np.uint32((1 << code.bits) - 1)).ravel()
    one = np.where(code.symbol < LITERALS, code.size, 0).astype(np.uint8)[window]
    # bits of one, two and four literals in a row; 0 where there are fewer
    one = np.concatenate([one, np.zeros(64, np.uint8)])
    here = np.arange(len(one) - 64)
    two = one[:-64] + (second := one[here + one[:-64]])
    two = np.concatenate([np.where((one[:-64] > 0) & (second > 0), two, 0).astype(np.uint8), np.zeros(64, np.uint8)])
    four = two[:-64] + (later := two[here + two[:-64]])
    four = np.where((two[:-64] > 0) & (later > 0), four, 0).astype(np.uint8).tobytes()
    step, end = one.tobytes(), len(four)
    at, parts, read, copies, n = bits.at & 7, [], 0, [], 0
    while n < total:  # where each symbol begins follows from the one before
        run: list[int] = []
        add, most = run.append, (total - n) // 4
        while len(run) < most and at < end and (size := four[at]):
            add(at)
            at += size
        if run:
            first = np.array(run, np.int64)
            third = first + two[first]
            parts.append(np.stack([first, first + one[first], third, third + one[third]], axis=1).ravel())
            read += 4 * len(run)
            n += 4 * len(run)
            if n == total:
                break
        if at >= end:
            raise ValueError("the stream ends early")
        if size := step[at]:
            parts.append(np.array([at]))
            at += size
            read += 1
            n += 1
            continue
        key = int(window[at])
        bits.at = begin * 8 + at + int(code.size[key])
        length = spread(int(code.symbol[key]) - LITERALS, bits)
        back = distance(spread(far.read(bits), bits), width)
        at = bits.at - begin * 8
        if back > n or n + length > total:
            raise ValueError("a back-reference leaves the image")
        copies.append((read, n, length, back))
        n += length
    bits.at = begin * 8 + at
    symbols = code.symbol[window[np.concatenate(parts)]].astype(np.uint8) if parts else np.zeros(0, np.uint8)
    if not copies:
        return symbols
    out, done, filled = np.empty(total, np.uint8), 0, 0
    for read, start, length, back in copies:
        out[filled:start] = symbols[done:read]
        past = out[start - back : start - back + min(back, length)]
        out[start : start + length] = past if back >= length else np.resize(past, length)
        done, filled = read, start + length
    out[filled:] = symbols[done:]
    return out


def channels(argb: np.ndarray) -> list[np.ndarray]:
    """Alpha, red, green, blue as signed numbers."""
    return [(argb >> np.uint32(s) & np.uint32(255)).astype(np.int64) for s in (24, 16, 8, 0)]


def merged(a, r, g, b) -> np.ndarray:
    return ((a & 255) << 24 | (r & 255) << 16 | (g & 255) << 8 | (b & 255)).astype(np.uint32)


def _signed(x: np.ndarray) -> np.ndarray:
    return (x & 255) - 256 * ((x & 255) > 127)


def enlarge(small: np.ndarray, bits: int, height: int, width: int) -> np.ndarray:
    return np.repeat(np.repeat(small, 1 << bits, 0), 1 << bits, 1)[:height, :width]


def cross_color(argb: np.ndarray, elements: np.ndarray, bits: int, sign: int) -> np.ndarray:
    """Adds (sign 1) or takes off (-1) what green says about red, and green and red about blue."""
    a, r, g, b = channels(argb)
    _, red_blue, green_blue, green_red = channels(enlarge(elements, bits, *argb.shape))
    delta = lambda t, c: _signed(t) * _signed(c) >> 5
    plain = r if sign < 0 else r + delta(green_red, g)
    return merged(a, plain if sign > 0 else r - delta(green_red, g), g, b + sign * (delta(green_blue, g) + delta(red_blue, plain)))


def subtract_green(argb: np.ndarray, sign: int) -> np.ndarray:
    a, r, g, b = channels(argb)
    return merged(a, r + sign * g, g, b + sign * g)


def _average(a: int, b: int) -> int:
    return (((a ^ b) & 0xFEFEFEFE) >> 1) + (a & b)


def _parts(c: int) -> tuple[int, int, int, int]:
    return c >> 24, c >> 16 & 255, c >> 8 & 255, c & 255


def _join(parts) -> int:
    a, r, g, b = parts
    return a << 24 | r << 16 | g << 8 | b


def predicted(mode: int, left: int, top: int, right: int, corner: int) -> int:
    """What a mode expects from the pixels left, above, above right and above left."""
    match mode:
        case 1:
            return left
        case 2:
            return top
        case 3:
            return right
        case 4:
            return corner
        case 5:
            return _average(_average(left, right), top)
        case 6:
            return _average(left, corner)
        case 7:
            return _average(left, top)
        case 8:
            return _average(corner, top)
        case 9:
            return _average(top, right)
        case 10:
            return _average(_average(left, corner), _average(top, right))
        case 11:
            far = sum(abs(t - c) - abs(x - c) for x, t, c in zip(_parts(left), _parts(top), _parts(corner), strict=True))
            return left if far < 0 else top
        case 12:
            return _join(min(255, max(0, x + t - c)) for x, t, c in zip(_parts(left), _parts(top), _parts(corner), strict=True))
        case 13:
            half = lambda m, c: m + int((m - c) / 2)  # noqa: E731  rounds to zero
            return _join(min(255, max(0, half(m, c))) for m, c in zip(_parts(_average(left, top)), _parts(corner), strict=True))
    return BLACK


def one_way(c: np.ndarray, mode: int, sign: int, alpha: bool) -> np.ndarray:
    """A channel under the predictor that looks left (1) or up (2) throughout, but along the first row or column."""
    first = 255 if alpha else 0
    along, edge = (1, np.s_[:, 0]) if mode == 1 else (0, np.s_[0])
    if sign > 0:
        out = c.copy()
        out[edge] = np.cumsum(c[edge]) + first
        return np.cumsum(out, axis=along)
    out = np.diff(c, axis=along, prepend=0)
    out[edge] = np.diff(c[edge], prepend=first)
    return out


def predictor(argb: np.ndarray, modes: np.ndarray, bits: int, sign: int) -> np.ndarray:
    """Adds predictions to residuals (sign 1), pixel after pixel, or takes them off an image (-1)."""
    height, width = argb.shape
    if ((modes >> 8 & 15) == (mode := int(modes.ravel()[0]) >> 8 & 15)).all() and mode in (1, 2):
        return merged(*(one_way(c, mode, sign, k == 0) for k, c in enumerate(channels(argb))))
    source, pick = argb.ravel().tolist(), (modes >> 8 & 15).tolist()
    out = [0] * len(source)
    known = out if sign > 0 else source
    for at in range(len(source)):
        y, x = divmod(at, width)
        if not y:
            guess = known[at - 1] if x else BLACK
        elif not x:
            guess = known[at - width]
        else:  # the pixel above right of the last column is the first of this row
            guess = predicted(pick[y >> bits][x >> bits], known[at - 1], known[at - width], known[at - width + 1], known[at - width - 1])
        p, s = _parts(guess), _parts(source[at])
        out[at] = _join((u + sign * v) & 255 for u, v in zip(s, p, strict=True))
    return np.array(out, np.uint32).reshape(height, width)


def packing(colors: int) -> int:
    """Base-2 logarithm of the pixels that share one, by the palette's size."""
    return 3 if colors <= 2 else 2 if colors <= 4 else 1 if colors <= 16 else 0


def from_palette(argb: np.ndarray, table: np.ndarray, width: int) -> np.ndarray:
    pack = packing(len(table))
    index = argb >> np.uint32(8) & np.uint32(255)
    if pack:
        each = 8 >> pack
        shifts = np.arange(1 << pack, dtype=np.uint32) * np.uint32(each)
        index = (index[:, :, None] >> shifts & np.uint32((1 << each) - 1)).reshape(len(index), -1)[:, :width]
    full = np.zeros(256, np.uint32)
    full[: len(table)] = table
    return full[index]


def decode(data: bytes) -> np.ndarray:
    """Pixels (height x width, ARGB) of a lossless WebP file."""
    return decode_at(data, 0)[0]


def decode_at(data: bytes, at: int) -> tuple[np.ndarray, int]:
    """Pixels of the file that begins at an offset, and where it ends."""
    if data[at : at + 4] != b"RIFF" or data[at + 8 : at + 16] != b"WEBPVP8L":
        raise ValueError("not a simple lossless WebP file")
    end = at + 8 + struct.unpack_from("<I", data, at + 4)[0]
    bits = Bits(data[at + 20 : at + 20 + struct.unpack_from("<I", data, at + 16)[0]])
    if bits.take(8) != SIGNATURE:
        raise ValueError("bad signature")
    width, height = bits.take(14) + 1, bits.take(14) + 1
    has_alpha = bits.take(1)
    if bits.take(3):
        raise ValueError("unknown version")
    undo, own = [], width
    while bits.take(1):
        kind = bits.take(2)
        if kind in (PREDICTOR, CROSS_COLOR):
            size = bits.take(3) + 2
            undo.append((kind, size, read_pixels(bits, blocks(own, size), blocks(height, size), False), own))
        elif kind == SUBTRACT_GREEN:
            undo.append((kind, 0, None, own))
        else:
            steps = read_pixels(bits, bits.take(8) + 1, 1, False)[0]
            table = merged(*(np.cumsum(c) for c in channels(steps)))
            undo.append((kind, 0, table, own))
            own = blocks(own, packing(len(table)))
    argb = read_pixels(bits, own, height, True)
    for kind, size, extra, wide in reversed(undo):
        if kind == PREDICTOR:
            argb = predictor(argb, extra, size, 1)
        elif kind == CROSS_COLOR:
            argb = cross_color(argb, extra, size, 1)
        elif kind == SUBTRACT_GREEN:
            argb = subtract_green(argb, 1)
        else:
            argb = from_palette(argb, extra, wide)
    return argb if has_alpha else argb | np.uint32(BLACK), end


# --- encoding -------------------------------------------------------------------------------------


def gather(value: int) -> tuple[int, int, int]:
    """Prefix, extra bits and their number, of a length or distance."""
    if value <= 4:
        return value - 1, 0, 0
    v = value - 1
    extra = v.bit_length() - 2
    prefix = 2 * (v.bit_length() - 1) + (v >> extra & 1)
    return prefix, v & ((1 << extra) - 1), extra


@dataclass
class Options:
    """What an image is written with. `copies`: (first pixel, pixels, distance), in order, apart."""

    transforms: list[tuple] = field(default_factory=list)  # (kind, bits, image) or (SUBTRACT_GREEN,) or (PALETTE, colours)
    cache_bits: int = 0
    copies: list[tuple[int, int, int]] = field(default_factory=list)
    groups: tuple[int, np.ndarray] | None = None  # (block bits, group of each block)
    alpha: bool = True


def write_pixels(w: Writer, argb: np.ndarray, main: bool, o: Options) -> None:
    height, width = argb.shape
    flat = argb.ravel().tolist()
    w.put(o.cache_bits > 0, 1)
    if o.cache_bits:
        w.put(o.cache_bits, 4)
    count = 1
    if main:
        w.put(o.groups is not None, 1)
        if o.groups is not None:
            w.put(o.groups[0] - 2, 3)
            write_pixels(w, o.groups[1].astype(np.uint32) << np.uint32(8) | np.uint32(BLACK), False, Options())
            count = int(o.groups[1].max()) + 1
    tokens, at, cache, copies = [], 0, [0] * (1 << o.cache_bits), {a: (n, d) for a, n, d in o.copies}
    shorts = {max(1, dx + dy * width): k + 1 for k, (dx, dy) in reversed(list(enumerate(NEAR)))}
    while at < len(flat):
        group = int(o.groups[1][at // width >> o.groups[0], at % width >> o.groups[0]]) if o.groups is not None and main else 0
        n = 1
        if at in copies:
            n, d = copies[at]
            tokens.append((group, gather(n), gather(shorts.get(d, d + len(NEAR)))))
        else:
            c = flat[at]
            slot = (c * CACHE_HASH & 0xFFFFFFFF) >> (32 - o.cache_bits) if o.cache_bits else 0
            tokens.append((group, slot, None) if o.cache_bits and cache[slot] == c else (group, _parts(c), 0))
        if o.cache_bits:
            for c in flat[at : at + n]:
                cache[(c * CACHE_HASH & 0xFFFFFFFF) >> (32 - o.cache_bits)] = c
        at += n
    sizes = (LITERALS + LENGTHS + (1 << o.cache_bits if o.cache_bits else 0), 256, 256, 256, DISTANCES)
    counts = [[[0] * n for n in sizes] for _ in range(count)]

    def symbols(what, far) -> list[tuple[int, int]]:
        if far is None:
            return [(0, LITERALS + LENGTHS + what)]
        if far == 0:
            a, r, g, b = what
            return [(0, g), (1, r), (2, b), (3, a)]
        return [(0, LITERALS + what[0]), (4, far[0])]

    for group, what, far in tokens:
        for k, s in symbols(what, far):
            counts[group][k][s] += 1
    codes = []
    for group in counts:
        codes.append([])
        for own in group:
            lengths, used = code_lengths(own), [s for s, n in enumerate(own) if n]
            write_code(w, lengths, used)
            codes[-1].append(list(zip(canonical(lengths), lengths, strict=True)))
    for group, what, far in tokens:
        for k, s in symbols(what, far):
            w.put(*codes[group][k][s])
            if far and k in (0, 4):
                w.put(*(what if k == 0 else far)[1:])


def file_of(stream: bytes) -> bytes:
    body = stream + bytes(len(stream) % 2)
    return b"RIFF" + struct.pack("<I", 12 + len(body)) + b"WEBPVP8L" + struct.pack("<I", len(stream)) + body


def encode(argb: np.ndarray, o: Options | None = None) -> bytes:
    """A lossless WebP file of the pixels (height x width, ARGB)."""
    o = o or Options()
    height, width = argb.shape
    w = Writer()
    for value, n in ((SIGNATURE, 8), (width - 1, 14), (height - 1, 14), (o.alpha, 1), (0, 3)):
        w.put(int(value), n)
    now = argb.astype(np.uint32)
    for kind, *more in o.transforms:
        w.put(1 | kind << 1, 3)
        if kind in (PREDICTOR, CROSS_COLOR):
            size, image = more
            w.put(size - 2, 3)
            write_pixels(w, image, False, Options())
            now = (predictor if kind == PREDICTOR else cross_color)(now, image, size, -1)
        elif kind == SUBTRACT_GREEN:
            now = subtract_green(now, -1)
        else:
            table = np.array(more[0], np.uint32)
            w.put(len(table) - 1, 8)
            write_pixels(w, merged(*(np.diff(c, prepend=0) for c in channels(table)))[None], False, Options())
            index = np.searchsorted(np.sort(table), now)
            index = np.argsort(table, kind="stable")[index]
            pack = packing(len(table))
            each, wide = 8 >> pack, blocks(now.shape[1], pack)
            padded = np.zeros((height, wide << pack), np.int64)
            padded[:, : now.shape[1]] = index
            packed = (padded.reshape(height, wide, 1 << pack) << (np.arange(1 << pack) * each)).sum(2)
            now = (packed.astype(np.uint32) << np.uint32(8)) | np.uint32(BLACK)
    w.put(0, 1)
    write_pixels(w, now, True, o)
    return file_of(w.bytes())


#: Samples that a copy replaces at least, and that it can replace at most.
LEAST_COPY, MOST_COPY = 24, 4096
#: Samples up to which the colour cache is tried.
TINY = 128


def repeats(flat: np.ndarray) -> list[tuple[int, int, int]]:
    """(first, samples, distance) of what was there before, in order: the nearest earlier place, taken as far as it goes."""
    n = len(flat) - LEAST_COPY + 1
    if n < 2:
        return []
    eight = np.lib.stride_tricks.as_strided(np.concatenate([flat, np.zeros(8, np.uint8)]).view(np.uint8), (len(flat), 8), (1, 1)).copy().view("<u8").ravel()
    with np.errstate(over="ignore"):  # a hash of LEAST_COPY samples; what it proposes is compared
        key = sum((eight[k : k + n] * np.uint64(0x9E3779B97F4A7C15 + 2 * k) for k in range(0, LEAST_COPY, 8)), np.zeros(n, np.uint64))
    order = np.argsort(key, kind="stable")
    same = key[order[1:]] == key[order[:-1]]
    if not same.any():
        return []
    before = np.full(n, -1, np.int64)
    before[order[1:][same]] = order[:-1][same]
    raw, out, at = flat.tobytes(), [], 0
    for k in np.flatnonzero(before >= 0).tolist():
        if k < at:
            continue
        start = int(before[k])
        size, most = LEAST_COPY, min(MOST_COPY, len(raw) - k)
        if raw[k : k + size] != raw[start : start + size]:
            continue
        while size < most:  # runs of equal bytes are compared in steps that shrink at the end
            more = min(64, most - size)
            while more and raw[k + size : k + size + more] != raw[start + size : start + size + more]:
                more //= 2
            if not more:
                break
            size += more
        out.append((k, size, k - start))
        at = k + size
    return out


@lru_cache(maxsize=64)
def short_codes(width: int) -> dict[int, int]:
    """Distances that have a short code in images of a width."""
    return {max(1, dx + dy * width): k + 1 for k, (dx, dy) in reversed(list(enumerate(NEAR)))}


def packed_bits(head: Writer, value: np.ndarray, size: np.ndarray) -> bytes:
    """The head's bits, then the values' one after the other."""
    end = head.n + np.cumsum(size)
    at = end - size
    total = (int(end[-1] if len(end) else head.n) + 7) // 8
    whole, shifted, byte = np.zeros(total + 4), value << (at & 7), at >> 3
    for k in range(4):  # bits of different symbols never meet, so sums are unions
        part = np.bincount(byte + k, weights=(shifted >> 8 * k & 255).astype(float))
        whole[: len(part)] += part[: len(whole)]
    out = whole[:total].astype(np.uint8)
    start = np.frombuffer(head.bytes(), np.uint8)
    out[: len(start)] |= start
    return out.tobytes()


def write_channel(w: Writer, flat: np.ndarray, width: int, alpha: int) -> bytes:
    """An image whose green alone varies, as literals and copies under one group of codes; vectorised."""
    copies = repeats(flat)
    literal = np.ones(len(flat), bool)
    for k, n, _ in copies:
        literal[k : k + n] = False
    where = np.flatnonzero(literal)
    shorts = short_codes(width)
    lengths = [gather(n) for _, n, _ in copies]
    backs = [gather(shorts.get(d, d + len(NEAR))) for *_, d in copies]
    counts = np.bincount(flat[where], minlength=LITERALS + LENGTHS)
    for prefix, *_ in lengths:
        counts[LITERALS + prefix] += 1
    far = np.bincount([x[0] for x in backs], minlength=DISTANCES) if backs else np.zeros(DISTANCES, np.int64)
    tables = []
    for own, constants in ((counts.tolist(), (0, 0, alpha)), (far.tolist(), ())):
        used = [k for k, n in enumerate(own) if n]
        size = code_lengths(own)
        write_code(w, size, used)
        tables.append((np.array(canonical(size) if len(used) > 1 else size, np.int64), np.array(size, np.int64)))
        for constant in constants:  # red, blue and alpha
            write_code(w, [0] * 256, [constant])
    # literals take one place, copies four, in the order of where they begin
    begins = np.array([k for k, *_ in copies], np.int64)
    place = np.arange(len(where)) + 4 * np.searchsorted(begins, where)
    value, bits = np.zeros(len(where) + 4 * len(copies), np.int64), np.zeros(len(where) + 4 * len(copies), np.int64)
    (codes, sizes), (far_codes, far_sizes) = tables
    value[place], bits[place] = codes[flat[where]], sizes[flat[where]]
    if copies:
        first = np.searchsorted(where, begins) + 4 * np.arange(len(copies))
        (p, x, e), (q, y, f) = (np.array(z, np.int64).T for z in (lengths, backs))
        for k, (v, n) in enumerate(((codes[LITERALS + p], sizes[LITERALS + p]), (x, e), (far_codes[q], far_sizes[q]), (y, f))):
            value[first + k], bits[first + k] = v, n
    return packed_bits(w, value, bits)


def entropy_bits(flat: np.ndarray) -> float:
    counts = np.bincount(flat.ravel())
    counts = counts[counts > 0]
    return float((counts * np.log2(counts.sum() / counts)).sum())


def encode_grey(samples: np.ndarray) -> bytes:
    """A grey image of the samples (height x width), in the way that seems shortest."""
    height, width = samples.shape
    values = np.flatnonzero(np.bincount(samples.ravel(), minlength=256))
    w = Writer()
    for value, n in ((SIGNATURE, 8), (width - 1, 14), (height - 1, 14), (0, 1), (0, 3)):
        w.put(value, n)
    wide, alpha = width, 255
    if len(values) <= 16:
        index, pack = np.searchsorted(values, samples).astype(np.int64), packing(len(values))
        each, wide = 8 >> pack, blocks(width, pack)
        padded = np.zeros((height, wide << pack), np.int64)
        padded[:, :width] = index
        green = (padded.reshape(height, wide, 1 << pack) << (np.arange(1 << pack) * each)).sum(2).astype(np.uint8) if pack else index.astype(np.uint8)
        grey = values.astype(np.uint32)
        w.put(1 | PALETTE << 1, 3)
        w.put(len(values) - 1, 8)
        write_pixels(w, merged(*(np.diff(c, prepend=0) for c in channels(np.uint32(BLACK) | grey << np.uint32(16) | grey << np.uint32(8) | grey)))[None], False, Options())
    else:
        w.put(1 | SUBTRACT_GREEN << 1, 3)
        signed, ways = samples.astype(np.int16), [samples]
        for mode in (1, 2):  # differences are looked at where most of them are small
            step = np.diff(signed, axis=2 - mode)
            ways.append(one_way(samples.astype(np.int64), mode, -1, False).astype(np.uint8) if 2 * np.count_nonzero(np.abs(step) <= 8) > step.size else None)
        cost = [entropy_bits(x) if x is not None else math.inf for x in (ways if any(x is not None for x in ways[1:]) else (None, None, None))]
        mode = min(range(3), key=lambda k: (cost[k] + 60 * (k > 0), k))
        green = ways[mode]
        if mode:
            size = 9  # the largest blocks
            w.put(1 | PREDICTOR << 1, 3)
            w.put(size - 2, 3)
            write_pixels(w, np.full((blocks(height, size), blocks(width, size)), BLACK | mode << 8, np.uint32), False, Options())
            alpha = 0
    w.put(0, 1)  # no more transforms
    best = Writer()
    best.value, best.n = w.value, w.n
    best.put(0, 2)  # no colour cache, no groups of codes
    out = write_channel(best, green.ravel(), wide, alpha)
    if samples.size <= TINY:
        argb = green.astype(np.uint32) << np.uint32(8) | np.uint32(alpha << 24)
        for bits in (1, 3):
            other = Writer()
            other.value, other.n = w.value, w.n
            write_pixels(other, argb, True, Options(cache_bits=bits))
            out = min(out, other.bytes(), key=len)
    return file_of(out)


def store(payload: bytes) -> bytes:
    """The payload (a multiple of COLUMNS) as grey images, one after the other."""
    most = COLUMNS * SIDE
    cut = [np.frombuffer(payload, np.uint8, min(most, len(payload) - at), at).reshape(-1, COLUMNS) for at in range(0, len(payload), most)]
    return b"".join(encode_grey(x) for x in cut)


def images(media: bytes) -> list[np.ndarray]:
    """Pixel arrays of stored images."""
    at, out = 0, []
    while at < len(media):
        argb, at = decode_at(media, at)
        out.append(argb)
    return out


def samples_of(arrays: list[np.ndarray]) -> bytes:
    return b"".join((argb >> np.uint32(8)).astype(np.uint8).tobytes() for argb in arrays)


def load(media: bytes) -> bytes:
    """The payload of stored images."""
    return samples_of(images(media))


def features(samples: np.ndarray) -> str:
    """Mean, deviation, entropy in bits and most frequent of the samples, and the mean step along rows."""
    counts = np.bincount(samples, minlength=256)
    p = counts[counts > 0] / len(samples)
    step = np.abs(np.diff(samples.astype(np.int16))).mean() if len(samples) > 1 else 0.0
    return f"mean={samples.mean():.4f};sd={samples.std():.4f};entropy={-(p * np.log2(p)).sum():.4f};mode={counts.argmax()};step={step:.4f}"


def padded(text: str | None) -> tuple[int, bytes]:
    raw = (text or "").encode("utf-8", "surrogatepass")
    return len(raw), raw + bytes(max(1, -(-len(raw) // COLUMNS)) * COLUMNS - len(raw))


def media_columns(docs: DataFrame, with_media: bool = False, with_pixels: bool = False) -> DataFrame:
    """doc_id, n_bytes, payload and media digests and features of every document.

    Optional: its media, and its decoded images as pixels: (height, width, ARGB of 4 bytes a pixel, little-endian).
    """
    schema = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string" + ", media binary" * with_media + ", images array<struct<height: int, width: int, argb: binary>>" * with_pixels

    def work(batch: pa.RecordBatch) -> dict:
        rows = []
        for text in batch.column("text").to_pylist():
            n, payload = padded(text)
            media = store(payload)
            arrays = images(media)
            back = samples_of(arrays)
            pixels = [{"height": x.shape[0], "width": x.shape[1], "argb": x.astype("<u4").tobytes()} for x in arrays] if with_pixels else None
            rows.append((n, len(payload), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-COLUMNS:]), len(media), hashlib.sha256(media).hexdigest(), features(np.frombuffer(back, np.uint8)), media, pixels))
        names = ("n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "media", "images")
        return {"doc_id": batch.column("doc_id")} | dict(zip(names, zip(*rows, strict=True) if rows else [[]] * len(names), strict=True))

    return map_rows(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), work, schema)
