"""Lossless WebP (VP8L): a full decoder, and an encoder for stored payloads and for tests.

The decoder reads prefix codes, meta prefix images, back-references and the colour cache, and
inverts the predictor, cross-colour, subtract-green and palette transforms. Where green is the
only coded channel, a table gives the code at every bit, and one pass walks from code to code.
Numbers and layouts follow the public bitstream specification.
"""

from __future__ import annotations

import struct
from functools import lru_cache
from itertools import repeat

import numpy as np

#: Fixed values of the bitstream.
LENGTH_ORDER = (17, 18, 0, 1, 2, 3, 4, 5, 16, 6, 7, 8, 9, 10, 11, 12, 13, 14, 15)
SIGNATURE = 0x2F
PREDICTOR, CROSS_COLOUR, SUBTRACT_GREEN, PALETTE = range(4)
CACHE_MULTIPLIER = 0x1E35A7BD
NEAR = (
    (0, 1), (1, 0), (1, 1), (-1, 1), (0, 2), (2, 0), (1, 2), (-1, 2), (2, 1), (-2, 1), (2, 2), (-2, 2), (0, 3), (3, 0), (1, 3), (-1, 3),
    (3, 1), (-3, 1), (2, 3), (-2, 3), (3, 2), (-3, 2), (0, 4), (4, 0), (1, 4), (-1, 4), (4, 1), (-4, 1), (3, 3), (-3, 3), (2, 4), (-2, 4),
    (4, 2), (-4, 2), (0, 5), (3, 4), (-3, 4), (4, 3), (-4, 3), (5, 0), (1, 5), (-1, 5), (5, 1), (-5, 1), (2, 5), (-2, 5), (5, 2), (-5, 2),
    (4, 4), (-4, 4), (3, 5), (-3, 5), (5, 3), (-5, 3), (0, 6), (6, 0), (1, 6), (-1, 6), (6, 1), (-6, 1), (2, 6), (-2, 6), (6, 2), (-6, 2),
    (4, 5), (-4, 5), (5, 4), (-5, 4), (3, 6), (-3, 6), (6, 3), (-6, 3), (0, 7), (7, 0), (1, 7), (-1, 7), (5, 5), (-5, 5), (7, 1), (-7, 1),
    (4, 6), (-4, 6), (6, 4), (-6, 4), (2, 7), (-2, 7), (7, 2), (-7, 2), (3, 7), (-3, 7), (7, 3), (-7, 3), (5, 6), (-5, 6), (6, 5), (-6, 5),
    (8, 0), (4, 7), (-4, 7), (7, 4), (-7, 4), (8, 1), (8, 2), (6, 6), (-6, 6), (8, 3), (5, 7), (-5, 7), (7, 5), (-7, 5), (8, 4), (6, 7),
    (-6, 7), (7, 6), (-7, 6), (8, 5), (7, 7), (-7, 7), (8, 6), (8, 7),
)


class Bits:
    """Reads bits from the low end of each byte upwards."""

    def __init__(self, data: bytes) -> None:
        self.data, self.at = data, 0

    def read(self, n: int) -> int:
        if not n:
            return 0
        first, last = self.at >> 3, (self.at + n + 7) >> 3
        if last > len(self.data):
            raise ValueError("the image ends early")
        value = int.from_bytes(self.data[first:last], "little") >> (self.at & 7)
        self.at += n
        return value & ((1 << n) - 1)


class Out:
    """Writes bits likewise."""

    def __init__(self) -> None:
        self.value = self.n = 0

    def write(self, value: int, n: int) -> None:
        self.value |= value << self.n
        self.n += n

    def codes(self, lengths: list[int], symbols) -> None:
        table = codes_of(tuple(lengths))
        for s in symbols:
            self.write(*table[s])

    def bytes(self) -> bytes:
        return self.value.to_bytes((self.n + 7) >> 3, "little")


@lru_cache(maxsize=1)
def _mirrored() -> list[int]:
    """All numbers of 15 bits with their bits in the other order."""
    every = np.arange(1 << 15)
    return sum((every >> k & 1) << (14 - k) for k in range(15)).tolist()


@lru_cache(maxsize=256)
def codes_of(lengths: tuple[int, ...]) -> dict[int, tuple[int, int]]:
    """Canonical code of each symbol as it lies in the stream, with its length; a lone symbol takes no bits."""
    used = [(n, s) for s, n in enumerate(lengths) if n]
    if len(used) == 1:
        return {used[0][1]: (0, 0)}
    if used and sum(1 << (15 - n) for n, _ in used) != 1 << 15:
        raise ValueError("the code is not complete")
    out, code, last, mirrored = {}, 0, 0, _mirrored()
    for n, s in sorted(used):
        code <<= n - last
        last = n
        out[s] = (mirrored[code] >> (15 - n), n)
        code += 1
    return out


class Prefix:
    """Decodes one prefix code: a table over ``width`` bits, longer codes bit by bit."""

    width = 8

    def __init__(self, lengths: tuple[int, ...]) -> None:
        self.lengths, codes = lengths, codes_of(lengths)
        self.single = next(iter(codes)) if len(codes) == 1 else 0 if not codes else None
        self.short: list[tuple[int, int] | None] = []

    def fill(self) -> None:
        codes = codes_of(self.lengths)
        self.long = {(c, n): s for s, (c, n) in codes.items()}
        self.short = [None] * (1 << self.width)
        for s, (c, n) in codes.items():
            if n <= self.width:
                self.short[c :: 1 << n] = [(s, n)] * (1 << (self.width - n))

    def read(self, bits: Bits) -> int:
        if self.single is not None:
            return self.single
        if not self.short:
            self.fill()
        at = bits.at
        window = int.from_bytes(bits.data[at >> 3 : (at >> 3) + 3], "little") >> (at & 7)
        if hit := self.short[window & 255]:
            bits.at = at + hit[1]
            if bits.at > len(bits.data) * 8:
                raise ValueError("the image ends early")
            return hit[0]
        for n in range(self.width + 1, 16):
            if (s := self.long.get((window & ((1 << n) - 1), n))) is not None:
                bits.at = at + n
                return s
        raise ValueError("no such code")


@lru_cache(maxsize=64)
def prefix(lengths: tuple[int, ...]) -> Prefix:
    return Prefix(lengths)


def read_code(bits: Bits, size: int) -> tuple[int, ...]:
    """The code lengths of the next prefix code over ``size`` symbols."""
    lengths = [0] * size
    if bits.read(1):
        two = bits.read(1)
        lengths[bits.read(8 if bits.read(1) else 1)] = 1
        if two:
            lengths[bits.read(8)] = 1
        return tuple(lengths)
    count = 4 + bits.read(4)
    own = [0] * 19
    for i in LENGTH_ORDER[:count]:
        own[i] = bits.read(3)
    most = 2 + bits.read(2 + 2 * bits.read(3)) if bits.read(1) else size
    code, i, last = Prefix(tuple(own)), 0, 8
    code.fill()
    short = code.short if code.single is None else [(code.single, 0)] * 256
    # what follows takes at most 14 bits a symbol
    window, at = int.from_bytes(bits.data[bits.at >> 3 : (bits.at + 14 * size + 7) >> 3], "little") >> (bits.at & 7), 0
    while i < size and most:
        most -= 1
        s, n = short[window >> at & 255]
        at += n
        if s < 16:
            lengths[i], i = s, i + 1
            last = s or last
            continue
        least, n = ((3, 2), (3, 3), (11, 7))[s - 16]
        n, at = least + (window >> at & ((1 << n) - 1)), at + n
        if i + n > size:
            raise ValueError("too many code lengths")
        lengths[i : i + n] = [last if s == 16 else 0] * n
        i += n
    bits.at += at
    if bits.at > len(bits.data) * 8:
        raise ValueError("the image ends early")
    return tuple(lengths)


def write_code(out: Out, lengths: list[int]) -> None:
    """The plain form for one or two small symbols, else all code lengths, with runs of zeros."""
    used = [s for s, n in enumerate(lengths) if n]
    if len(used) <= 2 and all(s < 256 for s in used):
        first = used[0] if used else 0
        out.write(1, 1), out.write(len(used) == 2, 1), out.write(first > 1, 1), out.write(first, 8 if first > 1 else 1)
        if len(used) == 2:
            out.write(used[1], 8)
        return
    tokens: list[tuple[int, int, int]] = []
    rest = bytes(lengths)
    while rest:
        n = min(138, len(rest) - len(rest.lstrip(b"\0")))
        if n >= 3:
            tokens.append((17, n - 3, 3) if n <= 10 else (18, n - 11, 7))
            rest = rest[n:]
        else:
            tokens.append((rest[0], 0, 0))
            rest = rest[1:]
    counts = [0] * 19
    for s, _, _ in tokens:
        counts[s] += 1
    own = huffman(counts, 7)
    out.write(0, 1), out.write(15, 4)
    for i in LENGTH_ORDER:
        out.write(own[i], 3)
    out.write(0, 1)
    table = codes_of(tuple(own))
    for s, extra, n in tokens:
        code, size = table[s]
        out.write(code | extra << size, size + n)


def huffman(counts: list[int], most: int = 15) -> list[int]:
    """Lengths of a complete code with none longer than ``most``; small counts are raised until that holds."""
    lengths, floor = [0] * len(counts), 1
    used = sorted((c, s) for s, c in enumerate(counts) if c)
    k = len(used)
    if k < 2:
        for _, s in used:
            lengths[s] = 1
        return lengths
    while True:
        weights = [max(c, floor) for c, _ in used]  # the leaves, then what they are joined to: both in order
        above, leaf, inner = [0] * (2 * k - 1), 0, k
        for node in range(k, 2 * k - 1):
            total = 0
            for _ in range(2):
                if leaf < k and (inner >= node or weights[leaf] <= weights[inner]):
                    at, leaf = leaf, leaf + 1
                else:
                    at, inner = inner, inner + 1
                above[at] = node
                total += weights[at]
            weights.append(total)
        depth = [0] * (2 * k - 1)
        for node in range(2 * k - 3, -1, -1):
            depth[node] = depth[above[node]] + 1
        if max(depth) <= most:
            for (_, s), n in zip(used, depth, strict=False):
                lengths[s] = n
            return lengths
        floor *= 2


# --- decoding -----------------------------------------------------------------------------


def _extra(bits: Bits, code: int) -> int:
    """A length or distance: a few codes stand for themselves, others add bits."""
    if code < 4:
        return code + 1
    n = (code - 2) >> 1
    return ((2 + (code & 1)) << n) + bits.read(n) + 1


#: Bytes of a stream whose codes are looked up at once.
WINDOW = 1 << 15


def _distance(bits: Bits, code: Prefix, width: int) -> int:
    d = _extra(bits, code.read(bits))
    if d > 120:
        return d - 120
    x, y = NEAR[d - 1]
    return max(1, x + y * width)


def _greens(bits: Bits, green: tuple[int, ...], distance: Prefix, width: int, total: int) -> np.ndarray:
    """The samples of an image whose other channels take no bits: literals and references."""
    most = max(green)
    table = np.zeros(1 << most, "<u2")  # the low byte of a symbol, and its bits above it; no bits mark a reference
    known = codes_of(green)
    for s, (code, n) in known.items():
        table[code :: 1 << n] = s | n << 8 if s < 256 else s - 256
    out, data, end = bytearray(), bits.data, len(bits.data) * 8
    add, at = out.append, bits.at
    while len(out) < total:
        if at >= end:
            raise ValueError("the image ends early")
        base = at >> 3
        raw = np.frombuffer(data[base : base + WINDOW + 2] + b"\0\0", np.uint8).astype(np.uint32)
        three = raw[:-2] | raw[1:-1] << np.uint32(8) | raw[2:] << np.uint32(16)
        codes = three[:WINDOW, None] >> np.arange(8, dtype=np.uint32)
        codes &= np.uint32((1 << most) - 1)
        pairs = table[codes.ravel()].tobytes()
        here, upto, low, step = at - base * 8, codes.size, pairs[::2], pairs[1::2] + bytes(16)
        while True:
            for _ in repeat(None, total - len(out)):
                n = step[here]
                if not n:
                    break
                add(low[here])
                here += n
            if here >= upto or len(out) == total:
                break
            s = 256 + low[here]
            bits.at = base * 8 + here + known[s][1]
            n = _extra(bits, s - 256)
            d = _distance(bits, distance, width)
            if d > len(out) or len(out) + n > total:
                raise ValueError("a reference leaves the image")
            first = len(out) - d
            out += out[first : first + n] if n <= d else (out[first:] * (n // d + 1))[:n]
            here = bits.at - base * 8
            if here >= upto:
                break
        at = base * 8 + here
    if at > end:
        raise ValueError("the image ends early")
    bits.at = at
    return np.frombuffer(out, np.uint8)


def _pixels(bits: Bits, width: int, height: int, main: bool) -> np.ndarray:
    """The entropy-coded pixels, as unsigned 32-bit ARGB in rows."""
    cache_bits = bits.read(4) if bits.read(1) else 0
    if cache_bits > 11:
        raise ValueError("the colour cache is too large")
    groups, meta, meta_bits, across = 1, None, 0, 0
    if main and bits.read(1):
        meta_bits = bits.read(3) + 2
        across = -(-width >> meta_bits)
        image = _pixels(bits, across, -(-height >> meta_bits), False)
        meta = (image >> 8 & 0xFFFF).astype(int).tolist()
        groups = max(meta) + 1
    cache_size = 1 << cache_bits if cache_bits else 0
    codes = [[prefix(read_code(bits, size)) for size in (256 + 24 + cache_size, 256, 256, 256, 40)] for _ in range(groups)]
    total = width * height
    if groups == 1 and not cache_bits and all(c.single is not None for c in codes[0][1:4]):
        red, blue, alpha = (c.single for c in codes[0][1:4])
        rest = np.uint32(alpha << 24 | red << 16 | blue)
        green = codes[0][0]
        if green.single is not None and green.single < 256:
            return np.full(total, rest | np.uint32(green.single << 8), np.uint32)
        if main:
            return _greens(bits, green.lengths, codes[0][4], width, total).astype(np.uint32) << np.uint32(8) | rest
    out = [0] * total
    cache = [0] * cache_size
    at = cached = 0

    def settle(upto: int) -> None:
        nonlocal cached
        while cached < upto:
            cache[(CACHE_MULTIPLIER * out[cached] & 0xFFFFFFFF) >> (32 - cache_bits)] = out[cached]
            cached += 1

    while at < total:
        group = codes[meta[(at // width >> meta_bits) * across + (at % width >> meta_bits)] if meta else 0]
        s = group[0].read(bits)
        if s < 256:
            red, blue, alpha = (group[k].read(bits) for k in (1, 2, 3))
            out[at] = alpha << 24 | red << 16 | s << 8 | blue
            at += 1
        elif s < 280:
            n = _extra(bits, s - 256)
            d = _distance(bits, group[4], width)
            if d > at or at + n > total:
                raise ValueError("a reference leaves the image")
            for _ in range(n):
                out[at] = out[at - d]
                at += 1
        else:
            settle(at)
            out[at] = cache[s - 280]
            at += 1
    return np.array(out, np.uint32)


def _channels(argb: np.ndarray) -> np.ndarray:
    return np.ascontiguousarray(argb, "<u4").view(np.uint8).reshape(*argb.shape, 4)[..., ::-1].astype(np.int64)


def _joined(c: np.ndarray) -> np.ndarray:
    c = c.astype(np.uint32) & np.uint32(255)
    return c[..., 0] << np.uint32(24) | c[..., 1] << np.uint32(16) | c[..., 2] << np.uint32(8) | c[..., 3]


def predict(mode: int, left: np.ndarray, top: np.ndarray, corner: np.ndarray, ahead: np.ndarray) -> np.ndarray:
    """The value that a mode expects from the four neighbours' channels."""
    half = lambda a, b: (a + b) >> 1
    if mode == 0:
        return np.array([255, 0, 0, 0])
    if mode in (1, 2, 3, 4):
        return (left, top, ahead, corner)[mode - 1]
    if mode == 5:
        return half(half(left, ahead), top)
    if mode in (6, 7, 8, 9):
        return half(*((left, corner), (left, top), (corner, top), (top, ahead))[mode - 6])
    if mode == 10:
        return half(half(left, corner), half(top, ahead))
    if mode == 11:
        return left if np.abs(top - corner).sum() < np.abs(left - corner).sum() else top
    if mode == 12:
        return np.clip(left + top - corner, 0, 255)
    if mode == 13:
        mean = half(left, top)
        d = mean - corner
        return np.clip(mean + np.where(d < 0, -(-d >> 1), d >> 1), 0, 255)
    raise ValueError("no such predictor")


def predicted(c: np.ndarray, modes: np.ndarray, bits: int, inverse: bool) -> np.ndarray:
    """Adds (inverse) or takes away the prediction of every pixel, in place order."""
    height, width = c.shape[:2]
    out = c.copy()
    if inverse and (modes == (mode := modes.flat[0])).all() and mode in (1, 2):  # sums along rows or columns
        out[0, 0, 0] += 255
        edge = (slice(None), 0) if mode == 1 else (0, slice(None))
        out[edge] = np.cumsum(out[edge], axis=0)
        return np.cumsum(out, axis=1 if mode == 1 else 0) & 255
    whole = out if inverse else c
    sign = 1 if inverse else -1
    for y in range(height):
        for x in range(width):
            if y == 0:
                p = np.array([255, 0, 0, 0]) if x == 0 else whole[0, x - 1]
            elif x == 0:
                p = whole[y - 1, 0]
            else:
                ahead = whole[y - 1, x + 1] if x + 1 < width else whole[y, 0]
                p = predict(int(modes[y >> bits, x >> bits]), whole[y, x - 1], whole[y - 1, x], whole[y - 1, x - 1], ahead)
            out[y, x] = (c[y, x] + sign * p) & 255
    return out


def _signed(a: np.ndarray) -> np.ndarray:
    return (a + 128 & 255) - 128


def recoloured(c: np.ndarray, grid: np.ndarray, bits: int, inverse: bool) -> np.ndarray:
    """Adds (inverse) or takes away what green and red say of red and blue; grid: red-to-blue, green-to-blue, green-to-red."""
    height, width = c.shape[:2]
    m = _signed(grid[np.arange(height)[:, None] >> bits, np.arange(width)[None, :] >> bits])
    r2b, g2b, g2r = m[..., 1], m[..., 2], m[..., 3]
    part = lambda t, v: t * _signed(v) >> 5
    red, green, blue = c[..., 1], c[..., 2], c[..., 3]
    sign = 1 if inverse else -1
    other = (red + sign * part(g2r, green)) & 255
    out = c.copy()
    out[..., 1] = other
    out[..., 3] = (blue + sign * (part(g2b, green) + part(r2b, other if inverse else red))) & 255
    return out


def pack_bits(colours: int) -> int:
    """How often the width of a palette image is halved."""
    return 3 if colours <= 2 else 2 if colours <= 4 else 1 if colours <= 16 else 0


def decode(image: bytes) -> np.ndarray:
    """The pixels of a lossless WebP file: height x width x (alpha, red, green, blue)."""
    if image[:4] != b"RIFF" or image[8:12] != b"WEBP":
        raise ValueError("not a WebP file")
    at, data = 12, None
    while at + 8 <= len(image) and data is None:
        n = struct.unpack("<I", image[at + 4 : at + 8])[0]
        data = image[at + 8 : at + 8 + n] if image[at : at + 4] == b"VP8L" else None
        at += 8 + n + (n & 1)
    if not data or data[0] != SIGNATURE:
        raise ValueError("no lossless image")
    bits = Bits(data)
    bits.read(8)
    width, height = bits.read(14) + 1, bits.read(14) + 1
    bits.read(1)
    if bits.read(3):
        raise ValueError("unknown version")
    undo, wide = [], width
    while bits.read(1):
        kind = bits.read(2)
        if kind in (k for k, *_ in undo):
            raise ValueError("a transform occurs twice")
        if kind in (PREDICTOR, CROSS_COLOUR):
            size = bits.read(3) + 2
            grid = _channels(_pixels(bits, -(-wide >> size), -(-height >> size), False)).reshape(-(-height >> size), -(-wide >> size), 4)
            undo.append((kind, wide, grid, size))
        elif kind == SUBTRACT_GREEN:
            undo.append((kind, wide, None, 0))
        else:
            n = bits.read(8) + 1
            colours = np.cumsum(_channels(_pixels(bits, n, 1, False)), axis=0) & 255
            undo.append((kind, wide, colours, pack_bits(n)))
            wide = -(-wide >> pack_bits(n))
    c = _channels(_pixels(bits, wide, height, True)).reshape(height, wide, 4)
    for kind, before, table, size in reversed(undo):
        if kind == PREDICTOR:
            c = predicted(c, table[..., 2] & 15, size, True)
        elif kind == CROSS_COLOUR:
            c = recoloured(c, table, size, True)
        elif kind == SUBTRACT_GREEN:
            c[..., 1] = (c[..., 1] + c[..., 2]) & 255
            c[..., 3] = (c[..., 3] + c[..., 2]) & 255
        else:
            each = 8 >> size
            index = (c[..., 2][..., None] >> (np.arange(1 << size) * each) & ((1 << each) - 1)).reshape(height, -1)[:, :before]
            c = np.vstack([table, np.zeros((256 - len(table), 4), np.int64)])[index]
    return c


# --- encoding -----------------------------------------------------------------------------


def container(data: bytes, *more: tuple[bytes, bytes]) -> bytes:
    body = b"".join(name + struct.pack("<I", len(x)) + x + b"\0" * (len(x) & 1) for name, x in ((b"VP8L", data), *more))
    return b"RIFF" + struct.pack("<I", 4 + len(body)) + b"WEBP" + body


def _head(out: Out, width: int, height: int) -> None:
    out.write(SIGNATURE, 8), out.write(width - 1, 14), out.write(height - 1, 14), out.write(0, 4)


def _write_pixels(out: Out, argb: np.ndarray, width: int, main: bool, cache_bits: int = 0, references: bool = False, groups: bool = False) -> None:
    """Entropy-codes pixels; with references, greedily to the last equal triple; with groups, odd and even tile rows have codes of their own."""
    px = [int(v) for v in argb.ravel()]
    tokens: list[tuple] = []
    cache, seen, i = {}, {}, 0
    while i < len(px):
        j = seen.get(tuple(px[i : i + 3])) if references and i + 3 <= len(px) else None
        n = 0
        while j is not None and i + n < len(px) and n < 4096 and px[j + n] == px[i + n]:
            n += 1
        slot = (CACHE_MULTIPLIER * px[i] & 0xFFFFFFFF) >> (32 - cache_bits) if cache_bits else -1
        if n >= 3:
            tokens.append((i, "copy", n, i - j))
        else:
            n = 1
            tokens.append((i, "cache", slot, 0) if cache_bits and cache.get(slot, 0) == px[i] else (i, "pixel", px[i], 0))
        for k in range(i, i + n):
            if cache_bits:
                cache[(CACHE_MULTIPLIER * px[k] & 0xFFFFFFFF) >> (32 - cache_bits)] = px[k]
            if k + 3 <= len(px):
                seen[tuple(px[k : k + 3])] = k
        i += n

    def spread(v: int) -> tuple[int, int, int]:
        """Code, extra bits and their number of a length or distance."""
        v -= 1
        if v < 4:
            return v, 0, 0
        top = v.bit_length() - 1
        return 2 * top + (v >> (top - 1) & 1), v & ((1 << (top - 1)) - 1), top - 1

    out.write(bool(cache_bits), 1)
    if cache_bits:
        out.write(cache_bits, 4)
    size, height = 2, -(-len(px) // width)
    group_of = (lambda at: (at // width >> size) & 1) if groups else (lambda at: 0)
    n_groups = 2 if groups and (height - 1) >> size else 1
    if main:
        out.write(n_groups > 1, 1)
        if n_groups > 1:
            out.write(size - 2, 3)
            across, down = -(-width >> size), -(-height >> size)
            _write_pixels(out, np.repeat((np.arange(down) & 1) << 8, across), across, False)
    counts = [[[0] * n for n in (280 + (1 << cache_bits if cache_bits else 0), 256, 256, 256, 40)] for _ in range(n_groups)]
    for at, kind, v, d in tokens:
        c = counts[group_of(at)]
        if kind == "pixel":
            for k, shift in enumerate((8, 16, 0, 24)):
                c[k][v >> shift & 255] += 1
        elif kind == "cache":
            c[0][280 + v] += 1
        else:
            c[0][256 + spread(v)[0]] += 1
            c[4][spread(d + 120)[0]] += 1
    lengths = [[huffman(x) for x in c] for c in counts]
    for group in lengths:
        for x in group:
            write_code(out, x)
    tables = [[codes_of(tuple(x)) for x in group] for group in lengths]
    for at, kind, v, d in tokens:
        t = tables[group_of(at)]
        if kind == "pixel":
            for k, shift in enumerate((8, 16, 0, 24)):
                out.write(*t[k][v >> shift & 255])
        elif kind == "cache":
            out.write(*t[0][280 + v])
        else:
            for table, base, value in ((t[0], 256, v), (t[4], 0, d + 120)):
                code, extra, n = spread(value)
                out.write(*table[base + code]), out.write(extra, n)


def encode(
    c: np.ndarray, predictor: np.ndarray | None = None, cross: np.ndarray | None = None, green: bool = False, palette: bool = False,
    tile: int = 2, cache_bits: int = 0, references: bool = False, groups: bool = False,
) -> bytes:
    """A lossless WebP file of small images (height x width x ARGB) with the named transforms and coding tools."""
    height, width = c.shape[:2]
    c = c.astype(np.int64)
    out = Out()
    _head(out, width, height)
    if palette:
        colours, index = np.unique(_joined(c).ravel(), return_inverse=True)
        if len(colours) > 256:
            raise ValueError("too many colours")
        out.write(1, 1), out.write(PALETTE, 2), out.write(len(colours) - 1, 8)
        steps = np.diff(_channels(colours), axis=0, prepend=0) & 255
        _write_pixels(out, _joined(steps), len(colours), False)
        shift = pack_bits(len(colours))
        per = 1 << shift
        rows = np.zeros((height, -(-width // per) * per), np.int64)
        rows[:, :width] = index.reshape(height, width)
        packed = (rows.reshape(height, -1, per) << (np.arange(per) * (8 >> shift))).sum(axis=2)
        c = np.zeros((*packed.shape, 4), np.int64)
        c[..., 0], c[..., 2] = 255, packed
        width = packed.shape[1]
    if predictor is not None:
        out.write(1, 1), out.write(PREDICTOR, 2), out.write(tile - 2, 3)
        grid = np.zeros((*predictor.shape, 4), np.int64)
        grid[..., 0], grid[..., 2] = 255, predictor
        _write_pixels(out, _joined(grid), predictor.shape[1], False)
        c = predicted(c, predictor, tile, False)
    if cross is not None:
        out.write(1, 1), out.write(CROSS_COLOUR, 2), out.write(tile - 2, 3)
        _write_pixels(out, _joined(cross), cross.shape[1], False)
        c = recoloured(c, cross, tile, False)
    if green:
        out.write(1, 1), out.write(SUBTRACT_GREEN, 2)
        c = c.copy()
        c[..., 1], c[..., 3] = (c[..., 1] - c[..., 2]) & 255, (c[..., 3] - c[..., 2]) & 255
    out.write(0, 1)
    _write_pixels(out, _joined(c), width, True, cache_bits, references, groups)
    return container(out.bytes())


#: Bytes that a reference repeats at least and, by the format, at most; and the farthest distance.
SHORTEST, LONGEST, FARTHEST = 8, 4096, (1 << 20) - 120


def references(samples: np.ndarray) -> np.ndarray:
    """Position, length and distance of copies, greedily from the left, each to the last place with the same eight bytes."""
    n = len(samples) - SHORTEST + 1
    if n < 2:
        return np.zeros((0, 3), np.int64)
    data = samples.tobytes()
    eights = np.ndarray((n,), "<u8", data, strides=(1,)).copy()
    # sorted by a hash, then by place, in one number
    mask = np.uint64((1 << n.bit_length()) - 1)
    keys = eights * np.uint64(0x9E3779B97F4A7C15) & ~mask | np.arange(n, dtype=np.uint64)
    keys.sort()
    same = np.flatnonzero((keys[1:] ^ keys[:-1]) <= mask)
    order = (keys & mask).astype(np.int64)
    later, earlier = order[same + 1], order[same]
    last = np.full(n, -1, np.int64)
    true = (eights[later] == eights[earlier]) & (later - earlier <= FARTHEST)
    last[later[true]] = earlier[true]
    found, at = [], 0
    places = np.flatnonzero(last >= 0)
    for i, j in zip(places.tolist(), last[places].tolist(), strict=True):
        if i < at:
            continue
        k, most = SHORTEST, min(LONGEST, len(data) - i)
        while k + 32 <= most and data[i + k : i + k + 32] == data[j + k : j + k + 32]:
            k += 32
        while k < most and data[i + k] == data[j + k]:
            k += 1
        found.append((i, k, i - j))
        at = i + k
    return np.array(found, np.int64).reshape(-1, 3)


def _split(v: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Code, extra bits and their number of lengths or distances."""
    v = v - 1
    more = np.maximum(np.frexp(v.astype(float))[1] - 2, 0)
    more[v < 4] = 0
    return np.where(v < 4, v, 2 * more + 2 + (v >> more & 1)), v & ((1 << more) - 1), more


def _about(counts: np.ndarray) -> float:
    """About how many bits a code of their own gives symbols: their entropy, but a bit each at least, if two differ."""
    c = counts[counts > 0]
    return float((c * np.maximum(1, np.log2(c.sum() / c))).sum()) if len(c) > 1 else 0.0


@lru_cache(maxsize=2)
def _lone(alpha: int) -> tuple[int, int]:
    """The codes of red, blue and alpha, which have one value each."""
    out = Out()
    for lone in (0, 0, alpha):
        write_code(out, [int(s == lone) for s in range(256)])
    return out.value, out.n


def _write_samples(out: Out, samples: np.ndarray, alpha: int = 255) -> bytes:
    """Appends an image of green samples with codes of its own, and references if they save bits."""
    copies = references(samples)
    inside = np.zeros(len(samples) + 1, np.int64)
    inside[copies[:, 0]] += 1
    inside[copies[:, 0] + copies[:, 1]] -= 1
    literals = np.flatnonzero(np.cumsum(inside[:-1]) == 0)
    length, distance = _split(copies[:, 1]), _split(copies[:, 2] + 120)
    counts = np.bincount(np.concatenate([samples[literals], 256 + length[0]]), minlength=280)
    far = np.bincount(distance[0], minlength=40)
    plain = np.bincount(samples, minlength=280)
    if _about(counts) + _about(far) + float(length[2].sum() + distance[2].sum()) >= _about(plain):
        copies, literals, counts, far = copies[:0], np.arange(len(samples)), plain, np.zeros(40, np.int64)
        length, distance = _split(copies[:, 1]), _split(copies[:, 2])
    green, apart = huffman(counts.tolist()), huffman(far.tolist())
    out.write(0, 2)  # no cache, one group
    write_code(out, green)
    out.write(*_lone(alpha))
    write_code(out, apart)

    def table(lengths: list[int]) -> tuple[np.ndarray, np.ndarray]:
        codes, sizes = [0] * len(lengths), [0] * len(lengths)
        for s, (code, n) in codes_of(tuple(lengths)).items():
            codes[s], sizes[s] = code, n
        return np.array(codes, np.uint64), np.array(sizes, np.int64)

    (codes, sizes), (far_codes, far_sizes) = table(green), table(apart)
    values, n = codes[samples[literals]], sizes[samples[literals]]
    if len(copies):
        whole = np.zeros((len(samples), 2), np.uint64), np.zeros((len(samples), 2), np.int64)
        whole[0][literals, 0], whole[1][literals, 0] = values, n
        for k, own, width, (symbol, extra, more) in ((0, codes[256:], sizes[256:], length), (1, far_codes, far_sizes, distance)):
            whole[0][copies[:, 0], k] = own[symbol] | extra.astype(np.uint64) << width[symbol].astype(np.uint64)
            whole[1][copies[:, 0], k] = width[symbol] + more
        taken = whole[1] > 0
        values, n = whole[0][taken], whole[1][taken]
    ends = np.cumsum(n)
    start = out.n + ends - n
    size = (out.n + int(ends[-1]) + 7) >> 3
    placed, first = values << (start & 31).astype(np.uint64), start >> 5
    # a part of up to 33 bits lies in two words at most; bits never overlap, so sums are unions
    words = np.bincount(first, weights=placed & np.uint64(0xFFFFFFFF), minlength=(size >> 2) + 2)
    words += np.bincount(first + 1, weights=placed >> np.uint64(32), minlength=len(words))
    body = words.astype("<u4").view(np.uint8)[:size]
    head = np.frombuffer(out.bytes(), np.uint8)
    body[: len(head)] |= head
    return body.tobytes()


def encode_samples(samples: np.ndarray, width: int) -> bytes:
    """The data of an image whose green samples are ``samples``, in rows of ``width``: the smallest of its forms.

    These are the plain one; differences to the left or upper sample, where these take fewer bits; and with at most 16
    different values a palette, which packs two to eight samples into one. The other tools never make such an image
    smaller, as its red, blue and alpha are constant, but for meta codes, which are not tried.
    """
    grid = samples.reshape(-1, width)
    height = len(grid)

    def start() -> Out:
        out = Out()
        _head(out, width, height)
        return out

    out = start()
    out.write(0, 1)
    forms = [_write_samples(out, samples)]
    counts = np.bincount(samples, minlength=256)
    bits = _about(counts)
    for mode in (1, 2):
        rest = grid.copy()
        rest[:, 1:], rest[1:, 0] = grid[:, 1:] - grid[:, :-1], grid[1:, 0] - grid[:-1, 0]
        if mode == 2:
            rest[1:] = grid[1:] - grid[:-1]
        if _about(np.bincount(rest.ravel(), minlength=256)) < bits:
            out, across = start(), -(-width >> 9)
            out.write(1, 1), out.write(PREDICTOR, 2), out.write(7, 3)
            _write_pixels(out, np.full(across * -(-height >> 9), 255 << 24 | mode << 8), across, False)
            out.write(0, 1)
            forms.append(_write_samples(out, rest.ravel(), 0))
    values = np.flatnonzero(counts)
    if shift := pack_bits(len(values)):
        out = start()
        out.write(1, 1), out.write(PALETTE, 2), out.write(len(values) - 1, 8)
        steps = np.zeros((len(values), 4), np.int64)
        steps[0, 0], steps[:, 2] = 255, np.diff(values, prepend=0)
        _write_pixels(out, _joined(steps), len(values), False)
        out.write(0, 1)
        rows = np.zeros((height, -(-width >> shift) << shift), np.uint8)
        rows[:, :width] = (np.cumsum(counts > 0) - 1)[grid]
        each = np.arange(1 << shift, dtype=np.uint8) * np.uint8(8 >> shift)
        forms.append(_write_samples(out, np.bitwise_or.reduce(rows.reshape(height, -1, 1 << shift) << each, axis=2).ravel()))
    return min(forms, key=len)
