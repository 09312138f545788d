"""Lossless WebP: a decoder for the whole lossless bit stream, and an encoder for byte payloads.

The decoder reads prefix codes (one group, or many by an entropy image), back-references with the plane distance codes, the
colour cache, and inverts the predictor, cross-colour, subtract-green and palette transforms.  With one group it works
on arrays: the length of the token that would start at each bit is looked up for all bits of a stretch, the starts that are
real are then followed one by one, and the tokens there are read together.  With many groups it reads pixel by pixel.

The encoder stores a payload as 8-bit samples, one to a pixel, and chooses from what the payload has: few different
bytes make a palette with several samples to a pixel, sequences that rise or repeat above each other a predictor, and repeats become
back-references.  Where three bytes to a pixel and a colour cache come out shorter by estimate, it stores that.  All prefix codes are
fitted to the counts.  A payload longer than one picture may be is a row of pictures.
"""

from __future__ import annotations

import hashlib
import zlib
from bisect import bisect_left
from itertools import groupby

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corridor.llm.texthash import bounded, small, tidy

# Fixed values of the format.
CODE_LENGTH_ORDER = (17, 18, 0, 1, 2, 3, 4, 5, 16, 6, 7, 8, 9, 10, 11, 12, 13, 14, 15)
PLANE_OFFSETS = (
    (0, 1), (1, 0), (1, 1), (-1, 1), (0, 2), (2, 0), (1, 2), (-1, 2), (2, 1), (-2, 1), (2, 2), (-2, 2), (0, 3), (3, 0), (1, 3), (-1, 3),
    (3, 1), (-3, 1), (2, 3), (-2, 3), (3, 2), (-3, 2), (0, 4), (4, 0), (1, 4), (-1, 4), (4, 1), (-4, 1), (3, 3), (-3, 3), (2, 4), (-2, 4),
    (4, 2), (-4, 2), (0, 5), (3, 4), (-3, 4), (4, 3), (-4, 3), (5, 0), (1, 5), (-1, 5), (5, 1), (-5, 1), (2, 5), (-2, 5), (5, 2), (-5, 2),
    (4, 4), (-4, 4), (3, 5), (-3, 5), (5, 3), (-5, 3), (0, 6), (6, 0), (1, 6), (-1, 6), (6, 1), (-6, 1), (2, 6), (-2, 6), (6, 2), (-6, 2),
    (4, 5), (-4, 5), (5, 4), (-5, 4), (3, 6), (-3, 6), (6, 3), (-6, 3), (0, 7), (7, 0), (1, 7), (-1, 7), (5, 5), (-5, 5), (7, 1), (-7, 1),
    (4, 6), (-4, 6), (6, 4), (-6, 4), (2, 7), (-2, 7), (7, 2), (-7, 2), (3, 7), (-3, 7), (7, 3), (-7, 3), (5, 6), (-5, 6), (6, 5), (-6, 5),
    (8, 0), (4, 7), (-4, 7), (7, 4), (-7, 4), (8, 1), (8, 2), (6, 6), (-6, 6), (8, 3), (5, 7), (-5, 7), (7, 5), (-7, 5), (8, 4), (6, 7),
    (-6, 7), (7, 6), (-7, 6), (8, 5), (7, 7), (-7, 7), (8, 6), (8, 7),
)
CACHE_MULTIPLIER = 0x1E35A7BD
LITERALS, LENGTH_CODES, DISTANCE_CODES = 256, 24, 40
MOST_LENGTH, MOST_DISTANCE = 4096, (1 << 20) - 120

ROW_BYTES = 576  # a row of samples
COLOURS = 192  # pixels of a row where three bytes make one
PICTURE_ROWS = 2048
MIN_MATCH, LONGEST_CODE, CACHE_BITS = 8, 12, 8
STRETCH = 1 << 15  # bytes of a stream that are looked at together


class Bits:
    """Little-endian bit reader."""

    def __init__(self, data: bytes) -> None:
        self.data, self.at, self.window, self.have = data, 0, 0, 0

    def read(self, n: int) -> int:
        if self.have < n:
            more = self.data[self.at : self.at + 32]
            self.window |= int.from_bytes(more, "little") << self.have
            self.have += 256  # past the end there are zeros
            self.at += 32
        out = self.window & ((1 << n) - 1)
        self.window >>= n
        self.have -= n
        return out

    def peek(self, n: int) -> int:
        if self.have < n:
            more = self.data[self.at : self.at + 32]
            self.window |= int.from_bytes(more, "little") << self.have
            self.have += 256
            self.at += 32
        return self.window & ((1 << n) - 1)

    def place(self) -> int:
        return self.at * 8 - self.have


_TURNED = np.array([int(f"{i:015b}"[::-1], 2) for i in range(1 << 15)])  # 15 bits in the other order
_TURNS = [_TURNED[: 1 << n] >> (15 - n) for n in range(16)]  # n bits in the other order


_NONE = np.zeros(1, np.int64)


def _in_code_order(lengths: list[int] | np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Symbols that have a code, shortest codes first, and their codes' lengths."""
    lengths = np.asarray(lengths)
    used = lengths.nonzero()[0]
    sizes = lengths.take(used)
    order = sizes.argsort(kind="stable")
    return used.take(order), sizes.take(order)


class PrefixCode:
    """Canonical code from lengths, as tables by the next ``most`` bits: symbol and length."""

    def __init__(self, lengths: list[int]) -> None:
        self.table = None
        symbols, sizes = _in_code_order(lengths)
        if len(symbols) < 2:  # takes no bits
            self.most, self.symbols, self.lengths = 0, symbols if len(symbols) else _NONE, _NONE
            return
        self.most = int(sizes[-1])
        share = 1 << (self.most - sizes)  # places of the table that each symbol has
        if share.sum() != 1 << self.most:
            raise ValueError("the code isn't complete")
        self.symbols = symbols.repeat(share).take(_TURNS[self.most])
        self.lengths = sizes.repeat(share).take(_TURNS[self.most])

    @classmethod
    def single(cls, symbol: int) -> PrefixCode:
        """The code of one symbol."""
        out = cls.__new__(cls)
        out.most, out.symbols, out.lengths, out.table = 0, np.array([symbol]), _NONE, None
        return out

    def read(self, bits: Bits) -> int:
        if self.table is None:
            self.table = list(zip(self.lengths.tolist(), self.symbols.tolist(), strict=True))
        n, s = self.table[bits.peek(self.most)]
        bits.window >>= n
        bits.have -= n
        return s

    def at(self, window: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Symbols and lengths of the codes that these windows of bits begin with."""
        i = window & ((1 << self.most) - 1)
        return self.symbols.take(i), self.lengths.take(i)


def read_code(bits: Bits, size: int) -> PrefixCode:
    if bits.read(1):
        two = bits.read(1)
        symbol = bits.read(8 if bits.read(1) else 1)
        if not two:
            return PrefixCode.single(symbol)
        lengths = [0] * max(size, 256)
        lengths[symbol] = 1
        lengths[bits.read(8)] = 1
        return PrefixCode(lengths)
    own = [0] * 19
    for i in range(4 + bits.read(4)):
        own[CODE_LENGTH_ORDER[i]] = bits.read(3)
    code = PrefixCode(own)
    left = 2 + bits.read(2 + 2 * bits.read(3)) if bits.read(1) else size
    lengths: list[int] = []
    last = 8
    table, mask = list(zip(code.lengths.tolist(), code.symbols.tolist(), strict=True)), (1 << code.most) - 1
    while len(lengths) < size and left:
        left -= 1
        n, s = table[(bits.window if bits.have > 15 else bits.peek(15)) & mask]
        bits.window >>= n
        bits.have -= n
        if s < 16:
            lengths.append(s)
            last = s or last
        elif s == 16:
            lengths += [last] * (3 + bits.read(2))
        else:
            lengths += [0] * (3 + bits.read(3) if s == 17 else 11 + bits.read(7))
    if len(lengths) > size:
        raise ValueError("too many code lengths")
    return PrefixCode(lengths + [0] * (size - len(lengths)))


def _value(prefix: int, bits: Bits) -> int:
    if prefix < 4:
        return prefix + 1
    extra = (prefix - 2) >> 1
    return ((2 + (prefix & 1)) << extra) + bits.read(extra) + 1


def _group(bits: Bits, cache_bits: int) -> list[PrefixCode]:
    sizes = (LITERALS + LENGTH_CODES + ((1 << cache_bits) if cache_bits else 0), LITERALS, LITERALS, LITERALS, DISTANCE_CODES)
    return [read_code(bits, n) for n in sizes]


def read_pixels(bits: Bits, width: int, height: int, top: bool) -> np.ndarray:
    """ARGB pixels of one entropy-coded picture, height x width, as unsigned 32-bit integers."""
    cache_bits = bits.read(4) if bits.read(1) else 0
    meta, shift = None, 0
    if top and bits.read(1):
        shift = 2 + bits.read(3)
        meta = (read_pixels(bits, -(-width >> shift), -(-height >> shift), False) >> 8) & 0xFFFF
    groups = [_group(bits, cache_bits) for _ in range(int(meta.max()) + 1 if meta is not None else 1)]
    g = groups[0]
    if meta is None:
        return read_group(bits, g, cache_bits, width, height)
    out = [0] * (width * height)
    cache = [0] * (1 << cache_bits) if cache_bits else []
    cache_shift = 32 - cache_bits
    at, cached, total = 0, 0, width * height
    while at < total:
        if meta is not None:
            g = groups[meta[(at // width) >> shift, (at % width) >> shift]]
        s = g[0].read(bits)
        if s < LITERALS:
            r, b, a = g[1].read(bits), g[2].read(bits), g[3].read(bits)
            out[at] = a << 24 | r << 16 | s << 8 | b
            at += 1
        elif s < LITERALS + LENGTH_CODES:
            n = _value(s - LITERALS, bits)
            d = _value(g[4].read(bits), bits)
            if d > len(PLANE_OFFSETS):
                d -= len(PLANE_OFFSETS)
            else:
                x, y = PLANE_OFFSETS[d - 1]
                d = max(1, x + y * width)
            if d > at or n > total - at:
                raise ValueError("a back-reference leaves the picture")
            for i in range(at, at + n):
                out[i] = out[i - d]
            at += n
        else:
            while cached < at:  # the cache takes in pixels when it is asked
                cache[(CACHE_MULTIPLIER * out[cached] & 0xFFFFFFFF) >> cache_shift] = out[cached]
                cached += 1
            out[at] = cache[s - LITERALS - LENGTH_CODES]
            at += 1
    return np.array(out, np.uint32).reshape(height, width)


_EXTRA = np.array([0, 0, 0, 0, *((p - 2) >> 1 for p in range(4, DISTANCE_CODES))])  # bits after a length or distance prefix
_FIRST = np.array([1, 2, 3, 4, *(((2 + (p & 1)) << ((p - 2) >> 1)) + 1 for p in range(4, DISTANCE_CODES))])  # the value if they are 0
_FAR = 1 << 20  # marks that a distance follows, twice that a cache entry is all
_GREEN_EXTRA = np.concatenate([np.zeros(LITERALS, np.int64), _FAR + _EXTRA[:LENGTH_CODES], [2 * _FAR]])
_EIGHT = np.arange(8)
_PLANE_X, _PLANE_Y = np.array(PLANE_OFFSETS).T


def _starts(after: np.ndarray, at: int) -> tuple[np.ndarray, int]:
    """Places of the tokens from ``at`` on, if the token at each place ends at ``after``, and where the last one ends."""
    end = len(after)
    step = np.concatenate([after, np.arange(end, end + 64)])  # beyond the end nothing moves
    two = step.take(step, mode="clip")
    four = two.take(two, mode="clip")
    eight, every = memoryview(four.take(four, mode="clip")), []
    see = every.append
    while at < end:
        see(at)
        at = eight[at]
    places = np.empty((8, len(every)), np.int64)
    places[0] = every
    for i in range(1, 8):
        step.take(places[i - 1], out=places[i], mode="clip")
    token = places.T.ravel()
    return token[: np.searchsorted(token, end)], at


def read_group(bits: Bits, group: list[PrefixCode], cache_bits: int, width: int, height: int) -> np.ndarray:
    """Pixels whose codes are all of one group."""
    green, red, blue, alpha, far = group
    total, done, place = width * height, 0, bits.place()
    out = np.zeros(total, np.uint32)
    if not (green.most or red.most or blue.most or alpha.most):  # no bits at all
        if green.symbols[0] < LITERALS:
            out[:] = _argb(green.symbols, red.symbols, blue.symbols, alpha.symbols)[0]
        return out.reshape(height, width)
    cache = [0] * (1 << cache_bits) if cache_bits else []
    cached = 0
    data = np.frombuffer(bits.data, np.uint8)
    # by the next bits: a token's length as far as the green code tells, more where a distance or nothing but a cache entry follows
    mask, lengths = (1 << green.most) - 1, green.lengths + _GREEN_EXTRA.take(green.symbols, mode="clip")
    far_mask, far_lengths = (1 << far.most) - 1, far.lengths + _EXTRA.take(far.symbols)
    rest = [code for code in (red, blue, alpha) if code.most]
    if cache_bits and not rest:  # a cache entry ends with its code, as a literal does
        lengths = np.where(lengths >= 2 * _FAR, lengths - 2 * _FAR, lengths)
    plain = None if rest or cache_bits else bytearray(total)  # only green differs from pixel to pixel
    while done < total:
        byte = place >> 3
        n = max(1, min(STRETCH, len(data) - byte + 1, (total - done) * 8 + 8))
        raw = np.zeros(n + 32, np.uint32)  # past the end there are zeros
        part = data[byte : byte + n + 32]
        raw[: len(part)] = part
        quad = raw[:-3] | raw[1:-2] << np.uint32(8) | raw[2:-1] << np.uint32(16) | raw[3:] << np.uint32(24)
        window = (quad.astype(np.int64)[:, None] >> _EIGHT).ravel()  # 25 bits and more from each bit on
        after = lengths.take(window[: 8 * n] & mask)
        back = (after >= _FAR).nonzero()[0]
        if rest:
            asked = (after[back] >= 2 * _FAR).nonzero()[0]
            asked, back = back[asked], np.delete(back, asked)
            after[asked] -= 2 * _FAR
            sizes = after[asked]
        after += np.arange(8 * n)  # where what follows the green code, and a length's own bits, starts
        here = after.take(back) - _FAR
        if rest:
            for code in rest:
                after += code.at(window.take(after, mode="clip"))[1]
            after[asked] = asked + sizes
        after[back] = here + far_lengths.take(window.take(here) & far_mask)
        token, at = _starts(after, place - 8 * byte)  # past the picture's end this reads on in vain; what it finds there is cut off below
        kind, first = green.at(window.take(token))
        first += token
        size = np.ones(len(token), np.int64)
        back = np.flatnonzero((kind >= LITERALS) & (kind < LITERALS + LENGTH_CODES))
        p, q = kind[back] - LITERALS, first[back]
        size[back] = _FIRST[p] + (window[q] & ((1 << _EXTRA[p]) - 1))
        q = q + _EXTRA[p]
        p, step = far.at(window[q])
        q = q + step
        distance = _FIRST[p] + (window[q] & ((1 << _EXTRA[p]) - 1))
        near = distance <= len(PLANE_OFFSETS)
        i = distance[near] - 1
        distance -= len(PLANE_OFFSETS)
        distance[near] = np.maximum(1, _PLANE_X[i] + _PLANE_Y[i] * width)
        to = done + np.cumsum(size)
        here = int(np.searchsorted(to, total)) + 1  # tokens that are still in the picture
        if here <= len(to):
            place = 8 * byte + int(after[token[here - 1]])
            if to[here - 1] > total:
                raise ValueError("a back-reference leaves the picture")
        else:
            place = 8 * byte + at
        begin = to - size
        literal = np.flatnonzero(kind[:here] < LITERALS)
        q = first[literal]
        channels = [kind[literal]]
        for code in (red, blue, alpha):
            if not code.most:
                channels.append(code.symbols)
                continue
            value, step = code.at(window[q])
            channels.append(value)
            q = q + step
        if plain is None:
            out[begin[literal]] = _argb(*channels)
        else:
            np.frombuffer(plain, np.uint8)[begin[literal]] = channels[0]
        inside = int(np.searchsorted(back, here))
        back, distance = back[:inside], distance[:inside]
        if (distance > begin[back]).any():
            raise ValueError("a back-reference leaves the picture")
        events = zip(begin[back].tolist(), size[back].tolist(), distance.tolist(), strict=True)
        if cache_bits:
            asked = np.flatnonzero(kind[:here] >= LITERALS + LENGTH_CODES)
            events = sorted([*events, *zip(begin[asked].tolist(), [0] * len(asked), (kind[asked] - LITERALS - LENGTH_CODES).tolist(), strict=True)])
        if plain is not None:
            for i, n, d in events:
                if n > d:  # repeats what it writes
                    plain[i : i + n] = (plain[i - d : i] * (n // d + 1))[:n]
                else:
                    plain[i : i + n] = plain[i - d : i - d + n]
            events = ()
        for i, n, d in events:
            if n > d:  # repeats what it writes
                out[i : i + n] = np.resize(out[i - d : i], n)
            elif n:
                out[i : i + n] = out[i - d : i - d + n]
            else:  # the cache takes in pixels when it is asked
                for v in out[cached:i].tolist():
                    cache[(CACHE_MULTIPLIER * v & 0xFFFFFFFF) >> (32 - cache_bits)] = v
                cached = i
                out[i] = cache[d]
        done = min(total, int(to[min(here, len(to)) - 1]))
    bits.at, bits.window, bits.have = place >> 3, 0, 0
    bits.read(place & 7)
    if plain is not None:
        out = _argb(np.frombuffer(plain, np.uint8), red.symbols, blue.symbols, alpha.symbols)
    return out.reshape(height, width)


def _argb(green, red, blue, alpha) -> np.ndarray:
    g, r, b, a = (np.asarray(x).astype(np.uint32) for x in (green, red, blue, alpha))
    return a << np.uint32(24) | r << np.uint32(16) | g << np.uint32(8) | b


def _channels(pixels: np.ndarray) -> np.ndarray:
    return np.ascontiguousarray(pixels.astype("<u4")).view(np.uint8).reshape(*pixels.shape, 4).astype(np.int32)  # b, g, r, a


def _pixels(c: np.ndarray) -> np.ndarray:
    return (c & 255).astype(np.uint8).reshape(*c.shape[:-1], 4).view("<u4")[..., 0]


def _average(a, b):
    return (a + b) >> 1


def _select(l, t, tl):  # noqa: E741
    return l if np.abs(t - tl).sum() < np.abs(l - tl).sum() else t


PREDICTORS = (
    lambda l, t, tr, tl: np.array([0, 0, 0, 255]),  # noqa: E741
    lambda l, t, tr, tl: l,  # noqa: E741
    lambda l, t, tr, tl: t,  # noqa: E741
    lambda l, t, tr, tl: tr,  # noqa: E741
    lambda l, t, tr, tl: tl,  # noqa: E741
    lambda l, t, tr, tl: _average(_average(l, tr), t),  # noqa: E741
    lambda l, t, tr, tl: _average(l, tl),  # noqa: E741
    lambda l, t, tr, tl: _average(l, t),  # noqa: E741
    lambda l, t, tr, tl: _average(tl, t),  # noqa: E741
    lambda l, t, tr, tl: _average(t, tr),  # noqa: E741
    lambda l, t, tr, tl: _average(_average(l, tl), _average(t, tr)),  # noqa: E741
    lambda l, t, tr, tl: _select(l, t, tl),  # noqa: E741
    lambda l, t, tr, tl: np.clip(l + t - tl, 0, 255),  # noqa: E741
    lambda l, t, tr, tl: np.clip(_average(l, t) + np.trunc((_average(l, t) - tl) / 2).astype(np.int32), 0, 255),  # noqa: E741
)


def invert_predictor(pixels: np.ndarray, modes: np.ndarray, shift: int) -> np.ndarray:
    c = _channels(pixels)
    height, width = pixels.shape
    c[0, 0] = (c[0, 0] + (0, 0, 0, 255)) & 255
    c[0] = np.cumsum(c[0], axis=0) & 255
    kinds = (modes >> 8) & 15
    if (kinds == 2).all():
        return _pixels(np.cumsum(c, axis=0))
    if (kinds == 1).all():
        c[:, 0] = np.cumsum(c[:, 0], axis=0) & 255
        c[1:] = np.cumsum(c[1:], axis=1)
        return _pixels(c)
    for y in range(1, height):
        row, up = c[y], c[y - 1]
        row[0] = (row[0] + up[0]) & 255
        for x in range(1, width):
            tr = up[x + 1] if x + 1 < width else row[0]
            mode = kinds[y >> shift, x >> shift]
            p = PREDICTORS[mode](row[x - 1], up[x], tr, up[x - 1]) if mode < 14 else PREDICTORS[0](0, 0, 0, 0)
            row[x] = (row[x] + p) & 255
    return _pixels(c)


def _signed(x: np.ndarray) -> np.ndarray:
    return x.astype(np.uint8).astype(np.int8).astype(np.int32)


def invert_cross_colour(pixels: np.ndarray, factors: np.ndarray, shift: int) -> np.ndarray:
    c = _channels(pixels)
    height, width = pixels.shape
    f = _channels(factors)[np.arange(height)[:, None] >> shift, np.arange(width)[None, :] >> shift]
    green = _signed(c[..., 1])
    c[..., 2] = (c[..., 2] + (_signed(f[..., 0]) * green >> 5)) & 255
    c[..., 0] += (_signed(f[..., 1]) * green >> 5) + (_signed(f[..., 2]) * _signed(c[..., 2]) >> 5)
    return _pixels(c)


def invert_subtract_green(pixels: np.ndarray) -> np.ndarray:
    c = _channels(pixels)
    c[..., 0] += c[..., 1]
    c[..., 2] += c[..., 1]
    return _pixels(c)


def invert_palette(pixels: np.ndarray, palette: np.ndarray, pack: int, width: int) -> np.ndarray:
    index = ((pixels >> 8) & 255).astype(np.int64)
    if pack:
        per, size = 1 << pack, 8 >> pack
        index = (index[..., None] >> (np.arange(per) * size)) & ((1 << size) - 1)
        index = index.reshape(len(pixels), -1)[:, :width]
    table = np.zeros(256, np.uint32)  # an index beyond the palette is transparent black
    table[: len(palette)] = palette
    return table[index]


def decode(data: bytes) -> np.ndarray:
    """ARGB pixels of a lossless WebP file, height x width."""
    if data[:4] != b"RIFF" or data[8:12] != b"WEBP":
        raise ValueError("not a WebP file")
    at = 12
    while data[at : at + 4] != b"VP8L":
        at += 8 + (int.from_bytes(data[at + 4 : at + 8], "little") + 1 & ~1)
        if at >= len(data):
            raise ValueError("no lossless picture")
    bits = Bits(data[at + 8 : at + 8 + int.from_bytes(data[at + 4 : at + 8], "little")])
    if bits.read(8) != 0x2F:
        raise ValueError("no lossless signature")
    width, height = bits.read(14) + 1, bits.read(14) + 1
    bits.read(1)
    if bits.read(3):
        raise ValueError("unknown version")
    undo, full = [], width
    while bits.read(1):
        kind = bits.read(2)
        if kind < 2:
            shift = 2 + bits.read(3)
            extra = read_pixels(bits, -(-width >> shift), -(-height >> shift), False)
            undo.append((invert_cross_colour if kind else invert_predictor, (extra, shift)))
        elif kind == 2:
            undo.append((invert_subtract_green, ()))
        else:
            n = bits.read(8) + 1
            palette = _pixels(np.cumsum(_channels(read_pixels(bits, n, 1, False)), axis=1))[0]
            pack = 3 if n <= 2 else 2 if n <= 4 else 1 if n <= 16 else 0
            undo.append((invert_palette, (palette, pack, width)))
            width = -(-width >> pack)
    pixels = read_pixels(bits, width, height, True)
    for f, args in reversed(undo):
        pixels = f(pixels, *args)
    assert pixels.shape == (height, full)
    return pixels


class BitWriter:
    def __init__(self) -> None:
        self.value, self.n = 0, 0

    def put(self, value: int, n: int) -> None:
        self.value |= value << self.n
        self.n += n

    def bits(self) -> np.ndarray:
        raw = np.frombuffer(self.value.to_bytes(self.n + 7 >> 3, "little"), np.uint8)
        return np.unpackbits(raw, bitorder="little")[: self.n]


def code_lengths(counts: np.ndarray, longest: int) -> list[int]:
    """Lengths of a complete prefix code fitted to the counts, none above ``longest``; a single symbol has length 1."""
    used = np.flatnonzero(counts).tolist()
    out = [0] * len(counts)
    if len(used) < 2:
        out[used[0] if used else 0] = 1
        return out
    weights, n = counts.take(used), len(used)
    while True:
        # leaves by weight, then joined pairs in the order they were made: both rise, so the two least are at the fronts
        order = weights.argsort(kind="stable")
        leaves = weights.take(order).tolist()
        joined, up, i, j = [leaves[0] + leaves[1]], [0] * n, 2, 0
        ups = [0] * (n - 1)
        lone = [*leaves, 1 << 62]
        for new in range(1, n - 1):
            a = lone[i]
            if a <= joined[j]:
                up[i], i = new, i + 1
            else:
                a, ups[j], j = joined[j], new, j + 1
            b = lone[i]
            if j == new or b <= joined[j]:
                up[i], i = new, i + 1
            else:
                b, ups[j], j = joined[j], new, j + 1
            joined.append(a + b)
        depth = [0] * (n - 1)
        for k in range(n - 3, -1, -1):
            depth[k] = depth[ups[k]] + 1
        if depth[up[0]] < longest:  # the lightest leaf is among the deepest
            break
        weights = (weights + 1) // 2 + 1  # flatter until it fits
    for s, u in zip(order.tolist(), up, strict=True):
        out[used[s]] = depth[u] + 1
    return out


def canonical(lengths: list[int]) -> tuple[np.ndarray, np.ndarray]:
    """For each symbol its code, first bit lowest, and the bits it takes: none where it is the only one."""
    codes, sizes = np.zeros(len(lengths), np.int64), np.zeros(len(lengths), np.int64)
    symbols, n = _in_code_order(lengths)
    if len(symbols) > 1:
        share = 1 << (15 - n)
        codes[symbols], sizes[symbols] = _TURNED.take(share.cumsum() - share), n
    return codes, sizes


def _runs(lengths: list[int]) -> list[tuple[int, int, int]]:
    """Code lengths as (symbol, extra, extra bits): runs of zeros and of the last length are shortened."""
    out, last = [], 8
    for n, run in groupby(lengths):
        left = len(list(run))
        if n and n != last:
            out.append((n, 0, 0))
            left, last = left - 1, n
        while left:
            if n == 0 and left > 2:
                take = min(left, 138)
                out.append((18, take - 11, 7) if take > 10 else (17, take - 3, 3))
            elif n and left > 2:
                take = min(left, 6)
                out.append((16, take - 3, 2))
            else:
                take = 1
                out.append((n, 0, 0))
            left -= take
    return out


def put_code(out: BitWriter, lengths: list[int]) -> None:
    used = [s for s, n in enumerate(lengths) if n]
    if len(used) <= 2 and used[-1] < LITERALS:
        out.put(1, 1)
        out.put(len(used) - 1, 1)
        out.put(1, 1)
        for s in used:
            out.put(s, 8)
        return
    runs = _runs(lengths)
    own = code_lengths(np.bincount([s for s, _, _ in runs], minlength=19), 7)
    codes, sizes = (x.tolist() for x in canonical(own))
    n = max(4, max(i + 1 for i, s in enumerate(CODE_LENGTH_ORDER) if own[s]))
    value, at = n - 4 << 1, 5
    for s in CODE_LENGTH_ORDER[:n]:
        value |= own[s] << at
        at += 3
    at += 1
    for s, extra, bits in runs:
        n = sizes[s]
        value |= (codes[s] | extra << n) << at
        at += n + bits
    out.put(value, at)


def pack(values: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Bits of values that take ``sizes`` bits each, lowest first."""
    out = []
    for a in range(0, len(values), 1 << 16):
        v, n = values[a : a + (1 << 16)], sizes[a : a + (1 << 16)]
        ends = np.cumsum(n)
        place = np.arange(ends[-1] if len(ends) else 0) - np.repeat(ends - n, n)
        out.append((np.repeat(v, n) >> place & 1).astype(np.uint8))
    return np.concatenate(out) if out else np.zeros(0, np.uint8)


def _prefix(values: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    u = np.maximum(values - 1, 1)
    top = np.frexp(u.astype(np.float64))[1].astype(np.int64) - 1
    bits = np.where(values <= 4, 0, top - 1)
    return np.where(values <= 4, values - 1, 2 * top + (u >> np.maximum(top - 1, 0) & 1)), np.where(values <= 4, 0, u & ((1 << np.maximum(bits, 0)) - 1)), bits


_PREFIXES = _prefix(np.arange(1 << 14))


def prefixes(values: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Prefix, extra bits' value and their number for lengths or distance codes from 1."""
    if values.max() >= len(_PREFIXES[0]):
        return _prefix(values)
    return _PREFIXES[0].take(values), _PREFIXES[1].take(values), _PREFIXES[2].take(values)


def matches(data: bytes) -> np.ndarray:
    """Repeats worth a back-reference, from left to right: start, length, distance."""
    n = len(data)
    if n <= MIN_MATCH:
        return np.zeros((0, 3), np.int64)
    key = np.ndarray(n - MIN_MATCH + 1, "<u8", data, strides=(1,)).copy()  # MIN_MATCH bytes from each on
    order = np.argsort((key * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(48)).astype(np.uint16), kind="stable")
    sorted_key = key.take(order)
    same = np.flatnonzero(sorted_key[1:] == sorted_key[:-1])
    before = np.full(len(key), -1, np.int64)
    before[order[same + 1]] = order[same]
    if n > MOST_DISTANCE:
        before[np.arange(len(key)) - before > MOST_DISTANCE] = -1
    found = []
    at = np.flatnonzero(before >= 0)
    before = before.take(at).tolist()
    at = at.tolist()
    number, here = int.from_bytes, 0
    while here < len(at):
        i, j = at[here], before[here]
        k, most = MIN_MATCH, min(MOST_LENGTH, n - i)
        while k < most:
            differ = number(data[i + k : i + k + 24], "little") ^ number(data[j + k : j + k + 24], "little")
            if differ:
                k += (differ & -differ).bit_length() - 1 >> 3
                break
            k += 24
        k = min(k, most)
        found.append((i, k, i - j))
        end = i + k
        here = bisect_left(at, end, here + 1)
    return np.array(found, np.int64).reshape(-1, 3)


def _lone(n: int, found: np.ndarray) -> np.ndarray:
    """Which of n places are in none of the repeats, which ascend and don't overlap."""
    turns = np.zeros((len(found) + 1, 2), np.int64)
    turns[:-1, 1] = found[:, 1]
    turns[:-1, 0] = found[:, 0]
    turns[-1, 0] = n
    turns[1:, 0] -= found[:, 0] + found[:, 1]
    return np.tile([True, False], len(turns)).repeat(turns.ravel())


_plane_codes: dict[int, dict[int, int]] = {}


def _distance_codes(distances: np.ndarray, width: int) -> np.ndarray:
    if width not in _plane_codes:
        near: dict[int, int] = {}
        for code, (x, y) in enumerate(PLANE_OFFSETS, 1):
            near.setdefault(max(1, x + y * width), code)
        _plane_codes[width] = near
    near = _plane_codes[width]
    return np.array([near.get(d, d + len(PLANE_OFFSETS)) for d in distances.tolist()], np.int64)


def _put_picture(out: BitWriter, top: bool, channels: list, cache_bits: int = 0, found: np.ndarray | None = None, asked: np.ndarray | None = None, width: int = 1) -> np.ndarray:
    """Header of an entropy-coded picture into ``out``; returns the bits of its pixels.

    channels: green of all pixels, then red, blue and alpha, or a number that all pixels have; found: back-references; asked: for each pixel
    its cache entry or -1.
    """
    kind = channels[0].astype(np.int64)
    token = None
    if found is not None and len(found):
        start, size, distance = found.T
        token = _lone(len(kind), found)
        token[start] = True
        lengths, far = prefixes(size), prefixes(_distance_codes(distance, width))
        kind[start] = LITERALS + lengths[0]
    if asked is not None:
        kind = np.where(asked >= 0, LITERALS + LENGTH_CODES + asked, kind)
    if token is not None:
        kind = kind[token]
        back = np.flatnonzero((kind >= LITERALS) & (kind < LITERALS + LENGTH_CODES))
    out.put(int(cache_bits > 0), 1)
    if cache_bits:
        out.put(cache_bits, 4)
    if top:
        out.put(0, 1)  # one group

    def coded(symbols: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
        own = code_lengths(np.bincount(symbols, minlength=size), LONGEST_CODE)
        put_code(out, own)
        codes, sizes = canonical(own)
        return codes.take(symbols), sizes.take(symbols)

    # a token's parts in the order they are read: green or length, its extra bits, red, blue, alpha, distance, its extra bits; 52 bits at most
    value, bits = coded(kind, LITERALS + LENGTH_CODES + (1 << cache_bits if cache_bits else 0))
    literal = None
    for c in channels[1:]:
        if isinstance(c, int):
            out.put(0b101 | c << 3, 11)  # a simple code of one symbol
            continue
        if literal is None:
            literal = np.flatnonzero(kind < LITERALS)
        v, n = coded((c if token is None else c[token])[literal], LITERALS)
        value[literal] |= v << bits[literal]
        bits[literal] += n
    if token is None:
        put_code(out, [1])
    else:
        v, n = value[back], bits[back]
        for more, size in ((lengths[1], lengths[2]), coded(far[0], DISTANCE_CODES), (far[1], far[2])):
            v, n = v | more << n, n + size
        value[back], bits[back] = v, n
    return pack(value, bits)


_C_LOG_C = np.concatenate([[0.0], np.arange(1, 1 << 12) * np.log2(np.arange(1, 1 << 12))])


def _entropy(counts: np.ndarray) -> float:
    """Bits that symbols of these counts take at best."""
    n = int(counts.sum())
    if n < len(_C_LOG_C):
        return float(_C_LOG_C[n] - _C_LOG_C.take(counts).sum())
    c = counts[counts > 0].astype(np.float64)
    return float((c * np.log2(n / c)).sum())


def file_of(bits: np.ndarray) -> bytes:
    body = np.packbits(bits, bitorder="little").tobytes()
    size = len(body)
    body += b"\0" * (size & 1)
    return b"RIFF" + (12 + len(body)).to_bytes(4, "little") + b"WEBPVP8L" + size.to_bytes(4, "little") + body


def head(out: BitWriter, width: int, height: int) -> None:
    out.put(0x2F, 8)
    out.put(width - 1, 14)
    out.put(height - 1, 14)
    out.put(0, 4)


def encode_rows(rows: np.ndarray) -> bytes:
    """One picture of payload rows, each of ROW_BYTES bytes, in the form that comes out shortest by estimate."""
    flat = rows.ravel()
    counts = np.bincount(flat, minlength=256)
    used = np.flatnonzero(counts)
    out = BitWriter()
    if len(used) <= 16:
        return _with_palette(out, rows, used)
    steps = {0: counts}
    for mode, axis in ((1, 1), (2, 0)):
        steps[mode] = np.bincount(np.diff(rows, axis=axis).ravel(), minlength=256) if rows.shape[axis] > 1 else counts
    mode = min(steps, key=lambda m: _entropy(steps[m]) * (1.0 if m == 0 else flat.size / max(1, steps[m].sum()) * 1.1))
    if mode:
        rows = _residual(rows, mode)
        flat = rows.ravel()
    data = flat.tobytes()
    found = matches(data)
    lone = flat[_lone(len(data), found)]
    cost = _entropy(np.bincount(lone)) + 20 * len(found)
    if not mode:  # three bytes to a pixel and a cache may be shorter
        with_cache = _with_cache(rows, cost)
        if with_cache is not None:
            return with_cache
    head(out, ROW_BYTES, len(rows))
    if mode:
        out.put(1, 1)
        out.put(0, 2)
        out.put(7, 3)  # one mode for blocks of 512 pixels, all the same
        blocks = -(-ROW_BYTES // 512) * -(-len(rows) // 512)
        _put_picture(out, False, _channels_of(np.full(blocks, mode)))  # one symbol: no bits follow
    out.put(0, 1)
    bits = _put_picture(out, True, _channels_of(flat, 0 if mode else 255), found=found, width=ROW_BYTES)  # a predictor starts from opaque black
    return file_of(np.concatenate([out.bits(), bits]))


def _channels_of(green: np.ndarray, alpha: int = 0) -> list:
    """Samples in green, one alpha, nothing else."""
    return [green, 0, 0, alpha]


def _residual(rows: np.ndarray, mode: int) -> np.ndarray:
    """What predictor 1, from the left, or 2, from above, leaves of the samples."""
    out = rows.copy()
    if mode == 2:
        out[1:] = rows[1:] - rows[:-1]
        out[0, 1:] = rows[0, 1:] - rows[0, :-1]
    else:
        out[:, 1:] = rows[:, 1:] - rows[:, :-1]
        out[1:, 0] = rows[1:, 0] - rows[:-1, 0]
    return out


def _with_palette(out: BitWriter, rows: np.ndarray, used: np.ndarray) -> bytes:
    """At most 16 different bytes: two, four or eight samples to a pixel, as indices of a palette."""
    head(out, ROW_BYTES, len(rows))
    out.put(1, 1)
    out.put(3, 2)
    out.put(len(used) - 1, 8)
    steps = np.diff(used, prepend=0)
    opaque = _channels_of(steps)
    opaque[3] = np.where(np.arange(len(used)) == 0, 255, 0)
    bits = _put_picture(out, False, opaque)
    for bit in bits.tolist():
        out.put(bit, 1)
    shift = 3 if len(used) <= 2 else 2 if len(used) <= 4 else 1
    per, size = 1 << shift, 8 >> shift
    place = np.zeros(256, np.uint8)
    place[used] = np.arange(len(used))
    index = place[rows].reshape(len(rows), -1, per).astype(np.uint16) << (np.arange(per, dtype=np.uint16) * size)
    index = index.sum(axis=2).astype(np.uint8)
    out.put(0, 1)
    found = matches(index.tobytes()) if len(used) > 1 else None
    bits = _put_picture(out, True, _channels_of(index.ravel()), found=found, width=index.shape[1])
    return file_of(np.concatenate([out.bits(), bits]))


def _with_cache(rows: np.ndarray, cost: float) -> bytes | None:
    """Three bytes to a pixel with a colour cache, if that takes fewer bits than ``cost`` by estimate."""
    colours = rows.reshape(-1, 3).astype(np.int64)
    argb = 0xFF << 24 | colours[:, 0] << 16 | colours[:, 1] << 8 | colours[:, 2]
    mixed = argb * CACHE_MULTIPLIER & 0xFFFFFFFF
    if 4 * np.count_nonzero(np.bincount(mixed >> 20)) > len(argb):  # most colours are new
        return None
    entry = mixed >> (32 - CACHE_BITS)
    order = np.argsort(entry.astype(np.uint8), kind="stable")
    hit = np.zeros(len(argb), bool)
    hit[order[1:]] = argb[order[1:]] == argb[order[:-1]]  # one colour has one entry
    kinds = np.concatenate([colours[~hit, 1], LITERALS + entry[hit]])
    if _entropy(np.bincount(kinds)) + sum(_entropy(np.bincount(colours[~hit, c])) for c in (0, 2)) >= cost:
        return None
    out = BitWriter()
    head(out, COLOURS, len(rows))
    out.put(0, 1)
    bits = _put_picture(out, True, [colours[:, 1], colours[:, 0], colours[:, 2], 255], CACHE_BITS, asked=np.where(hit, entry, -1))
    return file_of(np.concatenate([out.bits(), bits]))


def store(payload: np.ndarray) -> bytes:
    """A payload of a positive multiple of ROW_BYTES bytes as one or more pictures."""
    rows = payload.reshape(-1, ROW_BYTES)
    return b"".join(encode_rows(rows[a : a + PICTURE_ROWS]) for a in range(0, len(rows), PICTURE_ROWS))


def load(media: bytes) -> np.ndarray:
    """The payload's rows back from its pictures."""
    out, at = [], 0
    while at < len(media):
        size = 8 + int.from_bytes(media[at + 4 : at + 8], "little")
        p = decode(media[at : at + size])
        out.append((p >> 8).astype(np.uint8) if p.shape[1] == ROW_BYTES else np.stack([p >> 16, p >> 8, p], axis=-1).astype(np.uint8).reshape(len(p), ROW_BYTES))
        at += size
    return np.concatenate(out)


def feature(rows: np.ndarray) -> str:
    """Size, mean sample and mean step to the right neighbour, in hundredths, from the samples read back."""
    mean = int(rows.sum(dtype=np.int64)) * 100 // rows.size
    step = int(np.abs(np.diff(rows.astype(np.int16), axis=1)).sum(dtype=np.int64)) * 100 // (len(rows) * (ROW_BYTES - 1))
    return f"{ROW_BYTES}x{len(rows)} mean {mean} step {step}"


def media_columns(docs: DataFrame, with_media: bool = True) -> DataFrame:
    """Payload and picture figures of every row of ``docs(doc_id, text)``, and the stored bytes if wanted.

    The text's UTF-8 bytes (none if null) are padded with 255 to a positive multiple of 576, stored, read back from the
    stored bytes, and described from what was read.  Equal texts give equal values; a null doc_id stays null; an empty table gives an
    empty one.
    """
    names = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"] + ["media"] * with_media
    kinds = [pa.int64()] * 3 + [pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()] + [pa.binary()] * with_media

    def run(batches):
        for batch in small(batches):
            columns: list[list] = [[] for _ in names]
            for i, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                raw = (text.as_py() or "").encode()
                whole = max(1, -(-len(raw) // ROW_BYTES)) * ROW_BYTES
                media = store(np.frombuffer(raw + b"\xff" * (whole - len(raw)), np.uint8))
                rows = load(media)
                back = rows.tobytes()
                values = (i, len(raw), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-32:]), len(media), hashlib.sha256(media).hexdigest(), feature(rows), media)
                for c, v in zip(columns, values, strict=False):
                    c.append(v)
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names)

    schema = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string" + ", media binary" * with_media
    return bounded(docs).select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(tidy(run), schema)
