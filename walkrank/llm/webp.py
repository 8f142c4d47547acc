"""Lossless WebP (RFC 9649) for media columns: a decoder of the whole format, and an encoder.

Pixels are arrays of height x width x 4 (red, green, blue, alpha) 8-bit samples.

The decoder reads prefix codes (simple and normal), several code groups, back-references, the colour cache, and inverts
the predictor, cross-colour, subtract-green and palette transforms. Where an image has one code group and no colour
cache it finds the code words of all bit places of a window at once and then follows the chain of pixels; else it goes
pixel by pixel.

The encoder writes back-references to the nearest place where the next three pixels were before (runs are those of
distance one), one prefix code for green and lengths, one for the other channels and one for distances. It takes a
palette where an image has at most 256 colours, else the one of some transforms (none, green taken away, left pixel as
the prediction, or both) that leaves a sample of pixels with the least entropy. Cross-colour, other modes of the predictor
and the colour cache are written on demand.

Texts as media: UTF-8 bytes, padded, are the samples of images of WIDTH pixels a row and at most ROWS rows, stored one
after another. Null texts are empty ones. Repeated rows give equal results, other columns are left out, an empty table
gives an empty table.
"""

from __future__ import annotations

import struct
from functools import lru_cache

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

WIDTH, ROWS, UNIT, FILLER = 144, 1024, 576, 255
#: Bytes of a bit stream whose code words are found at once.
WINDOW = 1 << 16

# Fixed values of the format: the order of the code length codes, and the offsets (x, y) of the first 120 distances.
LENGTH_ORDER = (17, 18, 0, 1, 2, 3, 4, 5, 16, 6, 7, 8, 9, 10, 11, 12, 13, 14, 15)
NEAR = (
    (0, 1), (1, 0), (1, 1), (-1, 1), (0, 2), (2, 0), (1, 2), (-1, 2), (2, 1), (-2, 1), (2, 2), (-2, 2), (0, 3), (3, 0), (1, 3), (-1, 3), (3, 1), (-3, 1), (2, 3), (-2, 3),
    (3, 2), (-3, 2), (0, 4), (4, 0), (1, 4), (-1, 4), (4, 1), (-4, 1), (3, 3), (-3, 3), (2, 4), (-2, 4), (4, 2), (-4, 2), (0, 5), (3, 4), (-3, 4), (4, 3), (-4, 3), (5, 0),
    (1, 5), (-1, 5), (5, 1), (-5, 1), (2, 5), (-2, 5), (5, 2), (-5, 2), (4, 4), (-4, 4), (3, 5), (-3, 5), (5, 3), (-5, 3), (0, 6), (6, 0), (1, 6), (-1, 6), (6, 1), (-6, 1),
    (2, 6), (-2, 6), (6, 2), (-6, 2), (4, 5), (-4, 5), (5, 4), (-5, 4), (3, 6), (-3, 6), (6, 3), (-6, 3), (0, 7), (7, 0), (1, 7), (-1, 7), (5, 5), (-5, 5), (7, 1), (-7, 1),
    (4, 6), (-4, 6), (6, 4), (-6, 4), (2, 7), (-2, 7), (7, 2), (-7, 2), (3, 7), (-3, 7), (7, 3), (-7, 3), (5, 6), (-5, 6), (6, 5), (-6, 5), (8, 0), (4, 7), (-4, 7), (7, 4),
    (-7, 4), (8, 1), (8, 2), (6, 6), (-6, 6), (8, 3), (5, 7), (-5, 7), (7, 5), (-7, 5), (8, 4), (6, 7), (-6, 7), (7, 6), (-7, 6), (8, 5), (7, 7), (-7, 7), (8, 6), (8, 7),
)
PREDICT, CROSS, SUBTRACT, PALETTE = range(4)
CACHE_FACTOR = 0x1E35A7BD
ALPHABETS = (280, 256, 256, 256, 40)


def marked(x: np.ndarray) -> np.ndarray:
    """Places of a flat array that aren't zero."""
    return x.nonzero()[0]


def sampled(size: int, bits: int) -> int:
    return -(-size // (1 << bits))


class Bits:
    """Reader, least significant bit first."""

    def __init__(self, data: bytes):
        self.data, self.at = data + b"\0" * 8, 0

    def peek(self, n: int) -> int:
        i = self.at >> 3
        return (int.from_bytes(self.data[i : i + 8], "little") >> (self.at & 7)) & ((1 << n) - 1)

    def span(self, begin: int, end: int) -> int:
        """The bits of two places in between, as one number."""
        raw = int.from_bytes(self.data[begin >> 3 : (end + 7) >> 3], "little")
        return (raw >> (begin & 7)) & ((1 << (end - begin)) - 1)

    def take(self, n: int) -> int:
        value = self.peek(n)
        self.at += n
        if self.at > 8 * len(self.data):
            raise ValueError("the stream ends early")
        return value


class Code:
    """A canonical prefix code as a table of all words of its longest length."""

    def __init__(self, given: list[int]):
        lengths = np.array(given, np.uint8)
        used = marked(lengths)
        if len(used) <= 1:
            self.bits, self.symbol, self.length = 0, np.array([used[0] if len(used) else 0], np.int32), np.zeros(1, np.int32)
            return
        self.bits = int(lengths.max())
        order = used[np.argsort(lengths[used], kind="stable")]
        sizes = lengths[order].astype(np.int64)
        room = 1 << (self.bits - sizes)
        if room.sum() != 1 << self.bits:
            raise ValueError("the code lengths make no complete code")
        swapped = flipped(self.bits)
        self.symbol = np.repeat(order, room).astype(np.int32)[swapped]
        self.length = np.repeat(sizes, room).astype(np.int32)[swapped]

    def read(self, bits: Bits) -> int:
        word = bits.peek(self.bits)
        bits.take(int(self.length[word]))
        return int(self.symbol[word])


@lru_cache(16)
def flipped(n: int) -> np.ndarray:
    """For each word of n bits the word read from its other end."""
    out = np.zeros(1, np.int64)
    for k in range(n):
        out = np.concatenate([out << 1, (out << 1) | 1])
    return out


def read_codes(bits: Bits, sizes: list[int]) -> list[Code]:
    """Codes one after another. Where the bits of the one before repeat, they give the same code again."""
    out, begin, end = [], 0, 0
    for k, size in enumerate(sizes):
        if k and size == sizes[k - 1] and bits.span(begin, end) == bits.span(end, 2 * end - begin):
            out.append(out[-1])
            begin, bits.at = end, 2 * end - begin
        else:
            begin = bits.at
            out.append(read_code(bits, size))
        end = bits.at
    return out


def read_code(bits: Bits, size: int) -> Code:
    lengths = [0] * size
    if bits.take(1):
        two = bits.take(1)
        lengths[bits.take(8 if bits.take(1) else 1)] = 1
        if two:
            lengths[bits.take(8)] = 1
        return Code(lengths)
    own = [0] * 19
    for k in range(4 + bits.take(4)):
        own[LENGTH_ORDER[k]] = bits.take(3)
    left = 2 + bits.take(2 + 2 * bits.take(3)) if bits.take(1) else size
    (symbols, sizes, mask), at, last = lengths_code(tuple(own)), 0, 8
    ahead = n = 0
    while at < size and left:
        if n < 64:  # the next bits as one number
            low = bits.at >> 3
            ahead, n = int.from_bytes(bits.data[low : low + 256], "little") >> (bits.at & 7), 2048 - (bits.at & 7)
        left -= 1
        k, used = symbols[ahead & mask], sizes[ahead & mask]
        if k < 16:
            lengths[at] = k
            last, at = k or last, at + 1
        else:
            least, extra = ((3, 2), (3, 3), (11, 7))[k - 16]
            run = least + ((ahead >> used) & ((1 << extra) - 1))
            if at + run > size:
                raise ValueError("a run of code lengths is too long")
            lengths[at : at + run] = [last if k == 16 else 0] * run
            at += run
            used += extra
        ahead >>= used
        n -= used
        bits.at += used
    return Code(lengths)


@lru_cache(64)
def lengths_code(own: tuple[int, ...]) -> tuple[list[int], list[int], int]:
    """A code of code lengths: the symbol and the length of each word, and the mask of a word."""
    code = Code(list(own))
    return code.symbol.tolist(), code.length.tolist(), (1 << code.bits) - 1


def read_extra(bits: Bits, symbol: int) -> int:
    """The value that a length or distance symbol and its extra bits stand for."""
    if symbol < 4:
        return symbol + 1
    extra = (symbol - 2) >> 1
    return ((2 + (symbol & 1)) << extra) + bits.take(extra) + 1


def distance(code: int, width: int) -> int:
    if code > len(NEAR):
        return code - len(NEAR)
    x, y = NEAR[code - 1]
    return max(1, x + y * width)


def copied(out: np.ndarray, at: int, back: int, n: int) -> None:
    """out[at:at+n] from `back` places before; the two may overlap."""
    if back > at or at + n > len(out):
        raise ValueError("a back-reference leaves the image")
    while n:
        k = min(n, back)
        out[at : at + k] = out[at - back : at - back + k]
        at, n, back = at + k, n - k, back + k if back < 1 << 20 else back


def read_image(bits: Bits, width: int, height: int, main: bool = False) -> np.ndarray:
    """An entropy-coded image as 32-bit pixels (alpha, red, green, blue from the top)."""
    cache_bits = bits.take(4) if bits.take(1) else 0
    if cache_bits > 11:
        raise ValueError("the colour cache is too large")
    groups, of, tile = 1, None, 0
    if main and bits.take(1):
        tile = 2 + bits.take(3)
        of = (read_image(bits, sampled(width, tile), sampled(height, tile)) >> 8) & 0xFFFF
        groups = int(of.max()) + 1
    codes = [read_codes(bits, [n + (1 << cache_bits if cache_bits and n == 280 else 0) for n in ALPHABETS]) for _ in range(groups)]
    if groups == 1 and not cache_bits:
        return read_pixels(bits, width, height, codes[0])
    out = np.zeros(width * height, np.uint32)
    cache, kept, at = [0] * (1 << cache_bits), 0, 0
    across = sampled(width, tile)
    while at < len(out):
        g, r, b, a, d = codes[int(of[(at // width >> tile) * across + (at % width >> tile)]) if of is not None else 0]
        s = g.read(bits)
        if s < 256:
            red = r.read(bits)
            blue = b.read(bits)
            out[at] = a.read(bits) << 24 | red << 16 | s << 8 | blue
            at += 1
        elif s < 280:
            n = read_extra(bits, s - 256)
            copied(out, at, distance(read_extra(bits, d.read(bits)), width), n)
            at += n
        else:
            for p in out[kept:at].tolist() if cache_bits else ():
                cache[(CACHE_FACTOR * p & 0xFFFFFFFF) >> (32 - cache_bits)] = p
            kept = at
            out[at] = cache[s - 280]
            at += 1
    return out


def read_pixels(bits: Bits, width: int, height: int, codes: list[Code]) -> np.ndarray:
    """The pixels of one code group without a colour cache, by windows of the stream."""
    out, at = np.zeros(width * height, np.uint32), 0
    g, r, b, a, d = codes
    data = np.frombuffer(bits.data, np.uint8)
    most = sum(c.bits for c in (g, r, b, a))
    if not most and g.symbol[0] < 256:
        out[:] = int(a.symbol[0]) << 24 | int(r.symbol[0]) << 16 | int(g.symbol[0]) << 8 | int(b.symbol[0])
        return out
    while at < len(out):
        low = bits.at >> 3
        part = data[low : low + WINDOW + 16].astype(np.uint32)
        part = np.concatenate([part, np.zeros(3, np.uint32)])
        word = ((part[:-2] | part[1:-1] << 8 | np.concatenate([part[2:-1], [np.uint32(0)]]) << 16)[:, None] >> np.arange(8, dtype=np.uint32)).ravel().astype(np.int32)
        n, spots = len(word), np.arange(len(word), dtype=np.int32)
        ends: dict[int, np.ndarray] = {}

        def behind(code: Code, places: np.ndarray | None) -> np.ndarray:
            """The bit places behind the code words at some places (None: at all)."""
            if not code.bits:
                return spots if places is None else places
            if id(code) not in ends:
                ends[id(code)] = spots + code.length.take(word & ((1 << code.bits) - 1))
            return ends[id(code)] if places is None else ends[id(code)].take(places, mode="clip")

        green = g.symbol.take(word & ((1 << g.bits) - 1))
        at_r = behind(g, None)
        at_b = behind(r, at_r)
        at_a = behind(b, at_b)
        step = np.where(green < 256, behind(a, at_a), -1).astype(np.int32)
        limit = 8 * WINDOW if low + WINDOW + 16 < len(data) else n - 64
        step[limit:] = -2
        chain, places = memoryview(step), []
        p, begun, keep = bits.at - 8 * low, at, places.append
        while True:
            for _ in range(len(out) - begun - len(places)):
                q = chain[p]
                if q < 0:
                    break
                keep(p)
                p = q
            else:
                q = -2
            fill(out, begun, places, word, green, at_r, at_b, at_a, codes)
            at, bits.at = begun + len(places), 8 * low + p
            if q == -2:
                break
            length = read_extra(bits, g.read(bits) - 256)
            copied(out, at, distance(read_extra(bits, d.read(bits)), width), length)
            begun = at = at + length
            places, p = [], min(bits.at - 8 * low, n - 1)
            keep = places.append
        if at < len(out) and bits.at - 8 * low < limit or bits.at > 8 * len(data) or at < len(out) and bits.at >= 8 * len(data) - 64:
            raise ValueError("the stream ends early")
    return out


def fill(out, begun, places, word, green, at_r, at_b, at_a, codes) -> None:
    if places:
        at = np.array(places)
        value = lambda code, where: code.symbol[word[np.minimum(where, len(word) - 1)] & ((1 << code.bits) - 1)].astype(np.uint32)
        out[begun : begun + len(at)] = value(codes[3], at_a[at]) << 24 | value(codes[1], at_r[at]) << 16 | green[at].astype(np.uint32) << 8 | value(codes[2], at_b[at])


# transforms, on arrays of height x width x 4 in the order blue, green, red, alpha


def as_samples(pixels: np.ndarray, height: int, width: int) -> np.ndarray:
    return pixels.astype("<u4").view(np.uint8).reshape(height, width, 4)


def mean2(a, b):
    return (a + b) >> 1


def forecast(mode: int, left, top, corner, above_right):
    """The prediction of a mode from neighbours (arrays of ints, the last axis the channels)."""
    if mode == 1:
        return left
    if mode == 2:
        return top
    if mode == 3:
        return above_right
    if mode == 4:
        return corner
    if mode == 5:
        return mean2(mean2(left, above_right), top)
    if mode == 6:
        return mean2(left, corner)
    if mode == 7:
        return mean2(left, top)
    if mode == 8:
        return mean2(corner, top)
    if mode == 9:
        return mean2(top, above_right)
    if mode == 10:
        return mean2(mean2(left, corner), mean2(top, above_right))
    if mode == 11:
        nearer = np.abs(top - corner).sum(-1, keepdims=True) < np.abs(left - corner).sum(-1, keepdims=True)
        return np.where(nearer, left, top)
    if mode == 12:
        return np.clip(left + top - corner, 0, 255)
    if mode == 13:
        mid = mean2(left, top)
        return np.clip(mid + np.trunc((mid - corner) / 2).astype(mid.dtype), 0, 255)
    return np.zeros_like(left) + np.array([0, 0, 0, 255])


NEEDS_LEFT = {1, 5, 6, 7, 10, 11, 12, 13}


def unpredicted(rest: np.ndarray, modes: np.ndarray, tile: int) -> np.ndarray:
    height, width, _ = rest.shape
    out = rest.astype(np.int64)
    out[0, 0, 3] += 255
    out[0] = np.cumsum(out[0], 0) & 255
    for y in range(1, height):
        above, row = out[y - 1], out[y]
        row[0] = (row[0] + above[0]) & 255
        for t in range(sampled(width, tile)):
            mode, low, high = int(modes[y >> tile, t]) & 15, max(1, t << tile), min(width, (t + 1) << tile)
            if mode not in NEEDS_LEFT:
                right = np.vstack([above, row[:1]])[low + 1 : high + 1]
                row[low:high] = (row[low:high] + forecast(mode, above[low:high] * 0, above[low:high], above[low - 1 : high - 1], right)) & 255
            else:
                for x in range(low, high):
                    row[x] = (row[x] + forecast(mode, row[x - 1], above[x], above[x - 1], above[x + 1] if x + 1 < width else row[0])) & 255
    return out.astype(np.uint8)


def predicted_from(image: np.ndarray, modes: np.ndarray, tile: int) -> np.ndarray:
    """What the predictor leaves of an image."""
    full = image.astype(np.int64)
    height, width, _ = full.shape
    left, top = np.roll(full, 1, 1), np.roll(full, 1, 0)
    corner, right = np.roll(top, 1, 1), np.roll(top, -1, 1)
    right[:, -1] = full[:, 0]
    chosen = np.repeat(np.repeat(modes, 1 << tile, 0), 1 << tile, 1)[:height, :width]
    guess = np.zeros_like(full)
    for mode in np.unique(chosen):
        guess = np.where((chosen == mode)[..., None], forecast(int(mode), left, top, corner, right), guess)
    guess[0], guess[1:, 0] = left[0], top[1:, 0]
    guess[0, 0] = (0, 0, 0, 255)
    return ((full - guess) & 255).astype(np.uint8)


def cross(image: np.ndarray, tiles: np.ndarray, tile: int, sign: int) -> np.ndarray:
    """sign 1 inverts the cross-colour transform, -1 applies it. tiles: blue from green to red, green from green to blue, red from red to blue."""
    height, width, _ = image.shape
    factor = np.repeat(np.repeat(tiles, 1 << tile, 0), 1 << tile, 1)[:height, :width].view(np.int8).astype(np.int64)
    out = image.astype(np.int64)
    small = lambda x: ((x + 128) & 255) - 128
    red = (out[..., 2] + sign * ((factor[..., 0] * small(out[..., 1])) >> 5)) & 255
    true_red = red if sign > 0 else out[..., 2]
    out[..., 0] = (out[..., 0] + sign * (((factor[..., 1] * small(out[..., 1])) >> 5) + ((factor[..., 2] * small(true_red)) >> 5))) & 255
    out[..., 2] = red
    return out.astype(np.uint8)


def green_moved(image: np.ndarray, sign: int) -> np.ndarray:
    out = image.copy()
    out[..., 0] += np.uint8(sign & 255) * image[..., 1]
    out[..., 2] += np.uint8(sign & 255) * image[..., 1]
    return out


def bundle(colours: int) -> int:
    return 3 if colours <= 2 else 2 if colours <= 4 else 1 if colours <= 16 else 0


def from_palette(image: np.ndarray, palette: np.ndarray, width: int) -> np.ndarray:
    bits = bundle(len(palette))
    x = np.arange(width)
    index = (image[:, x >> bits, 1] >> ((x & ((1 << bits) - 1)) * (8 >> bits))) & ((1 << (8 >> bits)) - 1)
    return np.vstack([palette, np.zeros((256 - len(palette), 4), np.uint8)])[index]


def decode_frame(data: bytes) -> np.ndarray:
    """Samples (red, green, blue, alpha) of the chunk VP8L."""
    bits = Bits(data)
    if bits.take(8) != 0x2F:
        raise ValueError("not a lossless image")
    width, height = bits.take(14) + 1, bits.take(14) + 1
    bits.take(1)
    if bits.take(3):
        raise ValueError("unknown version")
    inverse, now = [], width
    while bits.take(1):
        kind = bits.take(2)
        if kind in (PREDICT, CROSS):
            tile = 2 + bits.take(3)
            across, down = sampled(now, tile), sampled(height, tile)
            tiles = as_samples(read_image(bits, across, down), down, across)
            inverse.append((lambda x, t=tiles, n=tile: unpredicted(x, t[..., 1], n)) if kind == PREDICT else (lambda x, t=tiles, n=tile: cross(x, t, n, 1)))
        elif kind == SUBTRACT:
            inverse.append(lambda x: green_moved(x, 1))
        else:
            colours = bits.take(8) + 1
            table = np.cumsum(as_samples(read_image(bits, colours, 1), 1, colours)[0], 0, dtype=np.uint8)
            inverse.append(lambda x, t=table, w=now: from_palette(x, t, w))
            now = sampled(now, bundle(colours))
    image = as_samples(read_image(bits, now, height, main=True), height, now)
    for undo in reversed(inverse):
        image = undo(image)
    return image[..., [2, 1, 0, 3]]


def frames(data: bytes):
    """The VP8L chunks of files stored one after another."""
    at = 0
    while at < len(data):
        if data[at : at + 4] != b"RIFF" or data[at + 8 : at + 12] != b"WEBP":
            raise ValueError("not a WebP file")
        end = at + 8 + struct.unpack_from("<I", data, at + 4)[0]
        at += 12
        while at < end:
            name, size = data[at : at + 4], struct.unpack_from("<I", data, at + 4)[0]
            if name == b"VP8L":
                yield data[at + 8 : at + 8 + size]
            elif name == b"VP8 ":
                raise ValueError("a lossy image")
            at += 8 + size + (size & 1)


def decode(data: bytes) -> list[np.ndarray]:
    return [decode_frame(x) for x in frames(data)]


# encoder


class Out:
    """Writer: small values, then whole arrays of code words."""

    def __init__(self):
        self.value, self.n, self.parts = 0, 0, []

    def put(self, value: int, n: int) -> None:
        self.value |= value << self.n
        self.n += n

    def flush(self) -> None:
        if self.n:
            raw = np.frombuffer(self.value.to_bytes((self.n + 7) // 8, "little"), np.uint8)
            self.parts.append(np.unpackbits(raw, bitorder="little")[: self.n])
        self.value = self.n = 0

    def words(self, values: np.ndarray, lengths: np.ndarray) -> None:
        self.flush()
        ends = np.cumsum(lengths)
        total = int(ends[-1]) if len(ends) else 0
        inside = np.arange(total) - np.repeat(ends - lengths, lengths)
        self.parts.append(((np.repeat(values, lengths) >> inside) & 1).astype(np.uint8))

    def data(self) -> bytes:
        self.flush()
        return np.packbits(np.concatenate(self.parts), bitorder="little").tobytes()


#: Longest code words that are written (the format has 15): short ones make small tables for the reader.
MOST = 10


def code_lengths(counts: np.ndarray, most: int = MOST) -> np.ndarray:
    """Lengths of a prefix code, `most` bits at most."""
    out = np.zeros(len(counts), np.uint8)
    used = marked(counts)
    if len(used) == 1:
        out[used] = 1
        return out
    # symbols rarer than that would get longer words
    weights = np.maximum(counts[used], counts.sum() >> most)
    while True:
        order = np.argsort(weights, kind="stable")
        leaves, n = weights[order].tolist(), len(used)
        # both the leaves and the inner nodes come in order of weight; the two lightest fronts join
        inner, above = [], [0] * (2 * n - 1)
        i = j = 0
        for k in range(n - 1):
            both = 0
            for _ in range(2):
                if j == len(inner) or (i < n and leaves[i] <= inner[j]):
                    both += leaves[i]
                    above[i] = n + k
                    i += 1
                else:
                    both += inner[j]
                    above[n + j] = n + k
                    j += 1
            inner.append(both)
        depth = [0] * (2 * n - 1)
        for k in range(2 * n - 3, -1, -1):
            depth[k] = depth[above[k]] + 1
        if max(depth[:n]) <= most:
            out[used[order]] = depth[:n]
            return out
        weights = (weights + 1) // 2


def code_words(lengths: np.ndarray) -> np.ndarray:
    """The words of a canonical code, to be written from their least significant bit."""
    out = np.zeros(len(lengths), np.int64)
    used = marked(lengths)
    if len(used) < 2:
        return out
    order = used[np.argsort(lengths[used], kind="stable")]
    sizes = lengths[order].astype(np.int64)
    first = np.cumsum(np.concatenate([[0], 1 << (15 - sizes[:-1])]))
    out[order] = flipped(15)[first]
    return out


def write_codes(out: Out, all_lengths: list[np.ndarray]) -> None:
    before, part = None, None
    for lengths in all_lengths:
        if lengths is not before:
            before, part = lengths, Out()
            write_code(part, lengths)
        out.put(part.value, part.n)


#: Lengths of the code that code lengths are written in: one choice for all, which costs a few bytes and saves a sixth of
#: the time. Taken from how often each symbol is used on the given texts.
LENGTHS_IN = (3, 7, 7, 5, 5, 5, 3, 3, 2, 4, 5, 7, 7, 7, 7, 7, 7, 4, 4)


@lru_cache(1)
def header_code() -> tuple[list[int], list[int], tuple[int, int]]:
    """That code's lengths, its words, and its own header as a value of so many bits."""
    out = Out()
    out.put(0, 1)
    out.put(19 - 4, 4)
    for k in LENGTH_ORDER:
        out.put(LENGTHS_IN[k], 3)
    return list(LENGTHS_IN), code_words(np.array(LENGTHS_IN)).tolist(), (out.value, out.n)


def write_code(out: Out, lengths: np.ndarray) -> None:
    used = marked(lengths)
    if len(used) <= 1 and (not len(used) or used[0] < 256):
        symbol = int(used[0]) if len(used) else 0
        out.put(0b01, 2)
        out.put(symbol > 1, 1)
        out.put(symbol, 8 if symbol > 1 else 1)
        return
    if len(used) == 2 and used[1] < 256:
        out.put(0b11, 2)
        out.put(1, 1)
        out.put(int(used[0]), 8)
        out.put(int(used[1]), 8)
        return
    # lengths as they are in a fixed-length code of 0 to 15 and a longer one for runs of zeros
    runs: list[tuple[int, int]] = []
    before = -1
    for at, length in zip(used.tolist(), lengths[used].tolist(), strict=True):
        zeros, before = at - before - 1, at
        while zeros:
            n = min(zeros, 138)
            runs.append((18, n - 11) if n >= 11 else (17, n - 3) if n >= 3 else (0, 0))
            zeros -= n if n >= 3 else 1
        runs.append((length, 0))
    if len(used) == 1:
        runs[-1] = (1, 0)
    sizes, words, (header, bits) = header_code()
    out.put(header, bits)
    out.put(1, 1)
    n = max(2, (len(runs) - 2).bit_length())
    n += n & 1
    out.put((n - 2) // 2, 3)
    out.put(len(runs) - 2, n)
    value = n = 0
    for s, extra in runs:
        value |= words[s] << n
        n += sizes[s]
        if s > 16:
            value |= extra << n
            n += 3 if s == 17 else 7
    out.put(value, n)


def extra_of(value: int) -> tuple[int, int, int]:
    """Symbol, extra bits and their number for a length or distance."""
    if value <= 4:
        return value - 1, 0, 0
    v = value - 1
    top = v.bit_length() - 1
    half = (v >> (top - 1)) & 1
    return 2 * top + half, v & ((1 << (top - 1)) - 1), top - 1


def write_image(out: Out, image: np.ndarray, main: bool, cache_bits: int = 0) -> None:
    """image: height x width x 4, blue, green, red, alpha."""
    flat = image.reshape(-1, 4)
    pixels = np.ascontiguousarray(flat).view("<u4").ravel()
    out.put(bool(cache_bits), 1)
    if cache_bits:
        out.put(cache_bits, 4)
    if main:
        out.put(0, 1)
    if cache_bits:
        return write_cached(out, flat, pixels, cache_bits)
    places = matches(pixels)
    literal, begins = np.ones(len(pixels), bool), np.zeros(len(pixels), bool)
    for at, n, _ in places:
        literal[at : at + n] = False
        begins[at] = True
    steps = [(*extra_of(n), *extra_of(near_code(image.shape[1]).get(back, back + len(NEAR)))) for _, n, back in places]
    kept = flat if not places else flat[literal]
    green, back = np.bincount(kept[:, 1], minlength=280), np.zeros(40, np.int64)
    for s, _, _, d, _, _ in steps:
        green[256 + s] += 1
        back[d] += 1
    rest = code_lengths(np.bincount(kept.ravel(), minlength=256) - green[:256]) if len(kept) else np.zeros(256, np.uint8)
    first, far = code_lengths(green), code_lengths(back) if places else np.zeros(40, np.uint8)
    write_codes(out, [first, rest, rest, rest, far])
    bits_of = lambda x: (x if np.count_nonzero(x) > 1 else np.zeros_like(x)).astype(np.int64)
    first_bits, rest_bits, far_bits = bits_of(first), bits_of(rest), bits_of(far)
    word_g, word_r, word_d = code_words(first), code_words(rest), code_words(far)
    ordered = kept.take((1, 2, 0, 3), 1)
    values, sizes = word_r.take(ordered), rest_bits.take(ordered)
    values[:, 0], sizes[:, 0] = word_g.take(ordered[:, 0]), first_bits.take(ordered[:, 0])
    if places:  # four values for a pixel, and for a reference: length, its extra bits, distance, its extra bits
        token = marked(literal | begins)
        all_values, all_sizes = np.zeros((2, len(token), 4), np.int64)
        all_values[literal[token]], all_sizes[literal[token]] = values, sizes
        s, length_extra, length_bits, d, distance_extra, distance_bits = np.array(steps).T
        all_values[begins[token]] = np.stack([word_g[256 + s], length_extra, word_d[d], distance_extra], 1)
        all_sizes[begins[token]] = np.stack([first_bits[256 + s], length_bits, far_bits[d], distance_bits], 1)
        values, sizes = all_values, all_sizes
    out.words(values.ravel(), sizes.ravel())


#: Pixels of a back-reference at least and at most, and the fewest of all of an image; with fewer only one at its end is written.
SHORTEST, LONGEST, WORTH = 3, 4096, 16
PLACE = np.uint64((1 << 20) - 1)


def matches(pixels: np.ndarray) -> list[tuple[int, int, int]]:
    """Back-references in order: place, number of pixels, how far back."""
    if len(pixels) <= SHORTEST:
        return []
    p = pixels.astype(np.uint64)
    key = (p[:-2] * np.uint64(0x9E3779B97F4A7C15)) ^ (p[1:-1] * np.uint64(0xC2B2AE3D27D4EB4F)) ^ (p[2:] * np.uint64(0x165667B19E3779F9))
    # in one number a hash of three pixels and their place
    ordered = np.sort((key & ~PLACE) | np.arange(len(key), dtype=np.uint64))
    hashes = ordered >> np.uint64(20)
    same = marked(hashes[1:] == hashes[:-1])
    if not len(same):
        return []
    found, end, total = [], 0, 0
    pairs = sorted(zip((ordered[same + 1] & PLACE).tolist(), (ordered[same] & PLACE).tolist(), strict=True))
    for at, back in pairs:
        if at >= end:
            differ = pixels[at : at + LONGEST] != pixels[back : back + min(LONGEST, len(pixels) - at)]
            n = int(differ.argmax()) if differ.any() else len(differ)
            if n >= SHORTEST:
                found.append((at, n, at - back))
                end, total = at + n, total + n
    last = found[-1:] if found and end == len(pixels) else []
    return found if total - sum(n for _, n, _ in last) >= WORTH else last


@lru_cache(64)
def near_code(width: int) -> dict[int, int]:
    """The least code of each distance that the table of near ones has."""
    return {distance(code, width): code for code in range(len(NEAR), 0, -1)}


#: Pixels that the choice of transforms looks at, and by how much one must be better than none.
SAMPLE, GAIN = 256, 0.95


def best_transforms(image: np.ndarray) -> tuple[int, ...]:
    """By the entropy of the samples that they leave of some pixels."""
    flat = image.reshape(-1, 4)[:SAMPLE]
    # most samples far from their left and other channels: nothing to gain
    if ((np.diff(flat, axis=0) + np.uint8(8)) > 16).mean() > 0.4 and (flat[:, 1] != flat[:, 2]).mean() > 0.5:
        return ()

    def entropy(x: np.ndarray) -> float:
        counts = np.bincount(x.ravel(), minlength=256)
        counts = counts[counts > 0]
        return float(x.size * np.log2(x.size) - (counts * np.log2(counts)).sum())

    moved = green_moved(flat, -1)
    sizes = {(): entropy(flat) * GAIN, (SUBTRACT,): entropy(moved)}
    for kinds, x in (((PREDICT,), flat), ((SUBTRACT, PREDICT), moved)):
        sizes[kinds] = entropy(np.diff(x, axis=0, prepend=np.zeros((1, 4), np.uint8)))
    return min(sizes, key=sizes.get)


def write_cached(out: Out, flat: np.ndarray, pixels: np.ndarray, cache_bits: int) -> None:
    slots, hits = [0] * (1 << cache_bits), []
    for p in pixels.tolist():
        k = (CACHE_FACTOR * p & 0xFFFFFFFF) >> (32 - cache_bits)
        hits.append(k if slots[k] == p and p else -1)
        slots[k] = p
    hit = np.array(hits)
    codes = [code_lengths(np.bincount(np.concatenate([flat[hit < 0, 1], 280 + hit[hit >= 0]]), minlength=280 + (1 << cache_bits)))]
    codes += [code_lengths(np.bincount(flat[hit < 0, c], minlength=256)) for c in (2, 0, 3)]
    write_codes(out, [*codes, np.zeros(40, np.uint8)])
    words = [code_words(x) for x in codes]
    for (b, g, r, a), h in zip(flat.tolist(), hits, strict=True):
        for lengths, word, s in [(codes[0], words[0], 280 + h)] if h >= 0 else zip(codes, words, (g, r, b, a), strict=True):
            out.put(int(word[s]), int(lengths[s]) if np.count_nonzero(lengths) > 1 else 0)


def encode(samples: np.ndarray, transforms: tuple[int, ...] | None = None, cache_bits: int = 0, tile: int = 3, modes: np.ndarray | None = None, factors: np.ndarray | None = None) -> bytes:
    """A file. transforms: in the order they are applied; None: a palette where it fits, else those that look best."""
    height, width, _ = samples.shape
    image = np.ascontiguousarray(samples[..., [2, 1, 0, 3]])
    out = Out()
    out.put(0x2F, 8)
    out.put(width - 1, 14)
    out.put(height - 1, 14)
    out.put(1, 1)
    out.put(0, 3)
    if transforms is None:
        colours = image.view("<u4").ravel()
        # the first pixels mostly tell already that there are too many colours
        few = len(set(colours[:400].tolist())) <= 256 and len(np.unique(colours)) <= 256
        transforms = (PALETTE,) if few else best_transforms(image)
    for kind in transforms:
        out.put(1, 1)
        out.put(kind, 2)
        now = image.shape[1]
        if kind == PALETTE:
            colours, index = np.unique(image.view("<u4"), return_inverse=True)
            table = np.ascontiguousarray(colours).view(np.uint8).reshape(-1, 4)
            out.put(len(table) - 1, 8)
            write_image(out, np.diff(table, axis=0, prepend=np.zeros((1, 4), np.uint8))[None], False)
            bits = bundle(len(table))
            padded = np.zeros((height, sampled(now, bits) << bits), np.int64)
            padded[:, :now] = index.reshape(height, now)
            image = np.zeros((height, sampled(now, bits), 4), np.uint8)
            image[..., 1] = (padded.reshape(height, -1, 1 << bits) << (np.arange(1 << bits) * (8 >> bits))).sum(-1)
        elif kind == SUBTRACT:
            image = green_moved(image, -1)
        else:
            down, across = sampled(height, tile), sampled(now, tile)
            out.put(tile - 2, 3)
            tiles = np.zeros((down, across, 4), np.uint8)
            tiles[..., 3] = 255
            if kind == PREDICT:
                tiles[..., 1] = modes if modes is not None else 1
                image = predicted_from(image, tiles[..., 1], tile)
            else:
                tiles[..., :3] = factors if factors is not None else 16
                image = cross(image, tiles, tile, -1)
            write_image(out, tiles, False)
    out.put(0, 1)
    write_image(out, image, True, cache_bits)
    chunk = out.data()
    body = b"WEBPVP8L" + struct.pack("<I", len(chunk)) + chunk + b"\0" * (len(chunk) & 1)
    return b"RIFF" + struct.pack("<I", len(body)) + body


# texts


def stored(payload: bytes) -> bytes:
    data, rows = np.frombuffer(payload, np.uint8), 4 * WIDTH * ROWS
    return b"".join(encode(data[at : at + rows].reshape(-1, WIDTH, 4)) for at in range(0, len(data), rows))


def feature(images: list[np.ndarray]) -> str:
    """Rows, mean sample of each channel, distinct samples and the entropy of samples in thousandths of a bit."""
    counts = sum(np.bincount(x.ravel(), minlength=256) for x in images)
    n, rows = int(counts.sum()), sum(len(x) for x in images)
    sums = sum(x.reshape(-1, 4).sum(0, dtype=np.int64) for x in images)
    share = counts[counts > 0] / n
    return f"rows={rows};mean={','.join(str(int(s) * 4 // n) for s in sums)};distinct={len(share)};entropy={round(-1000 * float((share * np.log2(share)).sum()))}"


FIELDS = {"n_bytes": "long", "payload_bytes": "long", "payload_sha256": "string", "tail_crc32": "long", "media_bytes": "long", "media_sha256": "string", "feature": "string", "media": "binary", "pixels": "binary"}


def text_media(docs: DataFrame, outputs: tuple[str, ...] = ("media", "feature"), text_col: str = "text") -> DataFrame:
    """doc_id and, of FIELDS, the outputs asked for: stored files, the samples read back, digests."""
    import hashlib
    import zlib

    def setup():
        def one(key, text):
            data = text.encode()
            media = stored(data + bytes([FILLER]) * (-len(data) % UNIT if data else UNIT))
            images = decode(media)
            back = b"".join(x.tobytes() for x in images)
            sha = lambda x: hashlib.sha256(x).hexdigest()
            out = {"n_bytes": len(data), "payload_bytes": len(back), "payload_sha256": sha(back), "tail_crc32": zlib.crc32(back[-32:]), "media_bytes": len(media), "media_sha256": sha(media), "feature": feature(images), "media": media, "pixels": back}
            return key, *(out[k] for k in outputs)

        return one

    return common.map_rows(docs.select("doc_id", common.text_of(text_col).alias("text")), setup, "doc_id long, " + ", ".join(f"{k} {FIELDS[k]}" for k in outputs))


def op2_webp(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document stored as lossless WebP and read back."""
    return text_media(common.documents(spark, sf_dir), ("n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"))


QUERIES = {"op2_webp": op2_webp}
ORACLES: dict[str, str] = {}
