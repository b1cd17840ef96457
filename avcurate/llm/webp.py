"""Lossless WebP (VP8L): a full decoder, and an encoder of byte payloads.

The decoder reads prefix codes (simple, normal, and several groups of them), back-references with
the two-dimensional distance codes, the colour cache, and inverts the predictor, cross-colour,
subtract-green and palette transforms. ``decode_payloads`` reads many images in step: those that
have one group of codes, no transform and no cache take one prefix code each at a time, by tables,
and their back-references are resolved together at the end. Where no code of an image has more than
one length and no back-reference or cache symbol can occur, all pixels are read at once; every
other image goes through the general loop.

The encoder stores bytes as the green channel of images ``WIDTH`` pixels wide. Of few different
bytes it makes a palette, with several pixels in one, and equally long codes. Any other payload gets
back-references for repeats of ``GRAM`` bytes or more and the cheapest of a few prefix codes
(``stock_codes``). Payloads of more than ``ROWS`` rows go on in further images, one container after
another, so that images in step are of like sizes. What is stored depends on the payload alone.

Edge cases: an empty payload is no image; a payload that is no multiple of WIDTH is refused; a
truncated or malformed image raises ValueError.
"""

from __future__ import annotations

import heapq
import struct
from collections.abc import Callable, Iterator
from functools import lru_cache

import numpy as np

WIDTH, ROWS = 192, 16
AT_ONCE = 1 << 20  # samples of the images that are made or read in step
GRAM, TABLE_BITS = 16, 13
#: Fixed values of the format: alphabet sizes, the order of code length codes, and the cache's multiplier.
LITERALS, LENGTH_CODES, DISTANCE_CODES = 256, 24, 40
CODE_LENGTH_ORDER = (17, 18, 0, 1, 2, 3, 4, 5, 16, 6, 7, 8, 9, 10, 11, 12, 13, 14, 15)
CACHE_MULTIPLIER = 0x1E35A7BD
#: Letters from the most to the least frequent, for the stock of prefix codes.
FREQUENT = b" etaoinsrhldcumfpgwybvkxjqz"
BLACK = 0xFF000000


@lru_cache(1)
def near_offsets() -> list[tuple[int, int]]:
    """The 120 nearby pixels that short distance codes name, nearest first."""
    all_ = [(x, y) for y in range(8) for x in range(-7, 9) if y or x > 0]
    return sorted(all_, key=lambda p: (p[0] ** 2 + p[1] ** 2, abs(p[0]), p[0] < 0))


class Bits:
    """Bits of a byte string, the lowest of each byte first."""

    def __init__(self, data: bytes):
        self.data, self.at, self.end = data, 0, 8 * len(data)

    def read(self, n: int) -> int:
        at = self.at
        self.at = at + n
        if self.at > self.end:
            raise ValueError("the image's bits end too early")
        return (int.from_bytes(self.data[at >> 3 : (at + n + 7) >> 3], "little") >> (at & 7)) & ((1 << n) - 1)


# --- prefix codes ----------------------------------------------------------------------------------


def reverse(code: int, n: int) -> int:
    return int(f"{code:0{n}b}"[::-1], 2) if n else 0


class Code:
    """A canonical prefix code; ``single`` is its only symbol, which takes no bits."""

    def __init__(self, lengths: list[int]):
        used = [(n, s) for s, n in enumerate(lengths) if n]
        if not used:
            used = [(0, 0)]
        self.single = used[0][1] if len(used) == 1 else None
        self.lookup: dict[tuple[int, int], int] = {}
        self.width = None
        self.symbols = [s for _, s in sorted(used)]
        if self.single is None:
            if sum(2.0**-n for n, _ in used) != 1:
                raise ValueError("a prefix code is not complete")
            code, before = 0, 0
            for n, s in sorted(used):
                code <<= n - before
                self.lookup[n, code] = s
                code, before = code + 1, n
            if used[0][0] == before == min(used)[0]:
                self.width = before

    def table(self) -> np.ndarray | None:
        """For each next TABLE_BITS bits the symbol times 16, plus its length; None where a length is above."""
        out = np.zeros(1 << TABLE_BITS, np.int32)
        if self.single is not None:
            out[:] = self.single << 4
            return out
        for (n, code), s in self.lookup.items():
            if n > TABLE_BITS:
                return None
            out[reverse(code, n) :: 1 << n] = s << 4 | n
        return out

    def read(self, bits: Bits) -> int:
        if self.single is not None:
            return self.single
        n = code = 0
        while n < 15:
            code, n = code << 1 | bits.read(1), n + 1
            if (s := self.lookup.get((n, code))) is not None:
                return s
        raise ValueError("no such prefix code")


@lru_cache(512)
def code_of(lengths: bytes) -> Code:
    return Code(list(lengths))


def read_code(bits: Bits, size: int) -> Code:
    lengths = bytearray(size)
    if bits.read(1):
        two = bits.read(1)
        for s in [bits.read(8 if bits.read(1) else 1), *([bits.read(8)] if two else [])]:
            lengths[s] = 1
        return code_of(bytes(lengths))
    of_lengths = bytearray(19)
    for i in range(4 + bits.read(4)):
        of_lengths[CODE_LENGTH_ORDER[i]] = bits.read(3)
    code = code_of(bytes(of_lengths))
    left = 2 + bits.read(2 + 2 * bits.read(3)) if bits.read(1) else size
    at, last = 0, 8
    if (n := code.single) is not None and n < 16:  # all lengths alike
        at, left = min(left, size), 0
        lengths[:at] = bytes([n]) * at
    while at < size and left > 0:
        left -= 1
        n = code.read(bits)
        if n < 16:
            lengths[at] = n
            at, last = at + 1, n or last
            continue
        times = {16: lambda: 3 + bits.read(2), 17: lambda: 3 + bits.read(3), 18: lambda: 11 + bits.read(7)}[n]()
        if at + times > size:
            raise ValueError("code lengths run over")
        lengths[at : at + times] = bytes([last if n == 16 else 0]) * times
        at += times
    return code_of(bytes(lengths))


# --- pixels ------------------------------------------------------------------------------------------


def _extra(bits: Bits, prefix: int) -> int:
    if prefix < 4:
        return prefix + 1
    n = (prefix - 2) >> 1
    return ((2 + (prefix & 1)) << n) + bits.read(n) + 1


def read_pixels(bits: Bits, width: int, height: int, top: bool) -> np.ndarray:
    """ARGB of an image part before its transforms are inverted; ``top``: it may have several code groups."""
    cache_bits = bits.read(4) if bits.read(1) else 0
    if cache_bits > 11:
        raise ValueError("the colour cache is too large")
    tile, groups_at, n_groups = 0, None, 1
    if top and bits.read(1):
        tile = bits.read(3) + 2
        tw, th = (width + (1 << tile) - 1) >> tile, (height + (1 << tile) - 1) >> tile
        groups_at = (read_pixels(bits, tw, th, False) >> 8 & 0xFFFF).reshape(th, tw)
        n_groups = int(groups_at.max()) + 1
    sizes = (LITERALS + LENGTH_CODES + (1 << cache_bits if cache_bits else 0), 256, 256, 256, DISTANCE_CODES)
    groups = [[read_code(bits, n) for n in sizes] for _ in range(n_groups)]
    n = width * height
    if n_groups == 1 and not cache_bits and _at_once(groups[0]):
        return _read_at_once(bits, groups[0], n)
    out, at = np.zeros(n, dtype=np.uint32), 0
    cache, shift = [0] * (1 << cache_bits), 32 - cache_bits
    while at < n:
        y, x = divmod(at, width)
        green, red, blue, alpha, dist = groups[int(groups_at[y >> tile, x >> tile]) if groups_at is not None else 0]
        s = green.read(bits)
        if s < LITERALS:
            r, b, a = red.read(bits), blue.read(bits), alpha.read(bits)
            new = [a << 24 | r << 16 | s << 8 | b]
        elif s < LITERALS + LENGTH_CODES:
            length = _extra(bits, s - LITERALS)
            d = _extra(bits, dist.read(bits))
            if d <= 120:
                dx, dy = near_offsets()[d - 1]
                d = max(1, dx + dy * width)
            else:
                d -= 120
            if d > at or at + length > n:
                raise ValueError("a back-reference leaves the image")
            new = [int(out[at - d + i % d]) for i in range(length)]
        else:
            new = [cache[s - LITERALS - LENGTH_CODES]]
        for p in new:
            out[at] = p
            at += 1
            if cache_bits:
                cache[(CACHE_MULTIPLIER * p & 0xFFFFFFFF) >> shift] = p
    return out


def _at_once(codes: list[Code]) -> bool:
    return all(c.single is not None or c.width for c in codes[:4]) and codes[0].symbols[-1] < LITERALS


def _read_at_once(bits: Bits, codes: list[Code], n: int) -> np.ndarray:
    order = [codes[i] for i in (0, 1, 2, 3)]
    widths = [c.width or 0 for c in order]
    total, start = sum(widths), bits.at
    bits.at += n * total
    if bits.at > bits.end:
        raise ValueError("the image's bits end too early")
    raw = np.frombuffer(bits.data, np.uint8, -(-bits.at // 8) - (start >> 3), start >> 3)
    flat = np.unpackbits(raw, bitorder="little")[start & 7 :][: n * total].reshape(n, total) if total else np.zeros((n, 0), np.uint8)
    out, at = np.zeros(n, dtype=np.uint32), 0
    for c, w, shift in zip(order, widths, (8, 16, 0, 24)):
        table = np.array(c.symbols if c.width else [c.single], dtype=np.uint32)
        index = np.packbits(flat[:, at : at + w], axis=1)[:, 0] >> (8 - w) if 0 < w <= 8 else np.zeros(n, np.uint8)
        if w > 8:
            index = flat[:, at : at + w].astype(np.uint32) @ (1 << np.arange(w - 1, -1, -1, dtype=np.uint32))
        out |= table[index] << np.uint32(shift)
        at += w
    return out


# --- transforms ----------------------------------------------------------------------------------------


def _channels(p: int) -> tuple[int, int, int, int]:
    return p >> 24, p >> 16 & 255, p >> 8 & 255, p & 255


def _pixel(c) -> int:
    return c[0] << 24 | c[1] << 16 | c[2] << 8 | c[3]


def _average(p: int, q: int) -> int:
    return _pixel([(a + b) // 2 for a, b in zip(_channels(p), _channels(q))])


def _clamp(v: int) -> int:
    return min(255, max(0, v))


def _select(left: int, top: int, corner: int) -> int:
    near = [0, 0]
    for a, b, c in zip(_channels(left), _channels(top), _channels(corner)):
        near[0] += abs(b - c)
        near[1] += abs(a - c)
    return left if near[0] < near[1] else top


def predict(mode: int, l: int, t: int, tl: int, tr: int) -> int:  # noqa: E741
    if mode in (0, 14, 15):
        return BLACK
    if mode < 5:
        return (l, t, tr, tl)[mode - 1]
    if mode == 5:
        return _average(_average(l, tr), t)
    if mode < 10:
        return _average(*((l, tl), (l, t), (tl, t), (t, tr))[mode - 6])
    if mode == 10:
        return _average(_average(l, tl), _average(t, tr))
    if mode == 11:
        return _select(l, t, tl)
    if mode == 12:
        return _pixel([_clamp(a + b - c) for a, b, c in zip(*map(_channels, (l, t, tl)))])
    mean = _average(l, t)
    return _pixel([_clamp(a + int((a - c) / 2)) for a, c in zip(_channels(mean), _channels(tl))])


def _add(p: int, q: int) -> int:
    return _pixel([(a + b) & 255 for a, b in zip(_channels(p), _channels(q))])


def undo_predictor(px: np.ndarray, modes: np.ndarray, tile: int) -> np.ndarray:
    h, w = px.shape
    out = [int(x) for x in px.ravel()]
    for y in range(h):
        for x in range(w):
            i = y * w + x
            if not y:
                guess = out[i - 1] if x else BLACK
            elif not x:
                guess = out[i - w]
            else:
                guess = predict(int(modes[y >> tile, x >> tile]) >> 8 & 15, out[i - 1], out[i - w], out[i - w - 1], out[i - w + 1])
            out[i] = _add(out[i], guess)
    return np.array(out, dtype=np.uint32).reshape(h, w)


def undo_cross_colour(px: np.ndarray, elements: np.ndarray, tile: int) -> np.ndarray:
    h, w = px.shape
    e = elements[np.arange(h)[:, None] >> tile, np.arange(w)[None, :] >> tile]
    signed = lambda v: (v & 255).astype(np.uint8).view(np.int8).astype(np.int32)
    green_red, green_blue, red_blue = signed(e), signed(e >> 8), signed(e >> 16)
    green = signed(px >> 8)
    red = ((px >> 16 & 255).astype(np.int32) + (green_red * green >> 5)) & 255
    blue = (px & 255).astype(np.int32) + (green_blue * green >> 5)
    blue = (blue + (red_blue * red.astype(np.uint8).view(np.int8).astype(np.int32) >> 5)) & 255
    return px & np.uint32(0xFF00FF00) | red.astype(np.uint32) << np.uint32(16) | blue.astype(np.uint32)


def undo_subtract_green(px: np.ndarray) -> np.ndarray:
    green = px >> 8 & 255
    return px & np.uint32(0xFF00FF00) | ((px >> 16) + green & 255) << np.uint32(16) | (px + green & 255)


def undo_palette(px: np.ndarray, palette: np.ndarray, width: int) -> np.ndarray:
    index = px >> 8 & 255
    if (shift := palette_shift(len(palette))) > 0:
        each = 8 >> shift
        part = np.arange(1 << shift, dtype=np.uint32) * each
        index = (index[:, :, None] >> part & (1 << each) - 1).reshape(len(px), -1)[:, :width]
    table = np.zeros(256, dtype=np.uint32)
    table[: len(palette)] = palette
    return table[index]


def palette_shift(colours: int) -> int:
    """How often halved the width is: with few colours several pixels share one."""
    return 3 if colours <= 2 else 2 if colours <= 4 else 1 if colours <= 16 else 0


# --- images ----------------------------------------------------------------------------------------------


def decode_vp8l(data: bytes) -> np.ndarray:
    """ARGB pixels, height x width."""
    bits = Bits(data)
    if bits.read(8) != 0x2F:
        raise ValueError("no lossless image")
    full, height = bits.read(14) + 1, bits.read(14) + 1
    bits.read(1)
    if bits.read(3):
        raise ValueError("unknown version")
    width, undo, seen = full, [], set()
    while bits.read(1):
        if (kind := bits.read(2)) in seen:
            raise ValueError("a transform comes twice")
        seen.add(kind)
        if kind < 2:
            tile = bits.read(3) + 2
            tw, th = (width + (1 << tile) - 1) >> tile, (height + (1 << tile) - 1) >> tile
            part = read_pixels(bits, tw, th, False).reshape(th, tw)
            undo.append((undo_predictor if kind == 0 else undo_cross_colour, part, tile))
        elif kind == 2:
            undo.append((undo_subtract_green,))
        else:
            n = bits.read(8) + 1
            channels = read_pixels(bits, n, 1, False).view(np.uint8).reshape(n, 4)
            palette = np.ascontiguousarray(np.cumsum(channels, axis=0, dtype=np.uint8)).view(np.uint32)[:, 0]
            undo.append((undo_palette, palette, width))
            shift = palette_shift(n)
            width = (width + (1 << shift) - 1) >> shift
    px = read_pixels(bits, width, height, True).reshape(height, width)
    for f, *more in reversed(undo):
        px = f(px, *more)
    return px


def containers(data: bytes):
    """The lossless streams of containers that follow one another."""
    at = 0
    while at < len(data):
        if data[at : at + 4] != b"RIFF" or data[at + 8 : at + 12] != b"WEBP":
            raise ValueError("no WebP container")
        end, p, found = at + 8 + struct.unpack_from("<I", data, at + 4)[0], at + 12, False
        if end > len(data):
            raise ValueError("a container is cut short")
        while p + 8 <= end:
            size = struct.unpack_from("<I", data, p + 4)[0]
            if data[p : p + 4] == b"VP8L":
                found = True
                yield data[p + 8 : p + 8 + size]
            p += 8 + size + (size & 1)
        if not found:
            raise ValueError("no lossless image in the container")
        at = end


def decode(data: bytes) -> np.ndarray:
    """ARGB pixels of a file with one image."""
    return decode_vp8l(next(containers(data)))


class BitWriter:
    def __init__(self):
        self.value = self.n = 0

    def put(self, value: int, n: int) -> None:
        self.value |= value << self.n
        self.n += n

    def one_symbol(self, s: int) -> None:
        self.put(1, 1)
        self.put(0, 1)
        self.put(1, 1)
        self.put(s, 8)

    def lengths(self, lengths: list[int]) -> None:
        """A code by its lengths, of up to 15 bits: each by a flat code of 4 bits, and runs of zeros by one of 5."""
        said, at = [], 0
        while at < len(lengths):
            run = next((k for k, n in enumerate(lengths[at : at + 138]) if n != lengths[at]), len(lengths[at : at + 138]))
            if lengths[at] == 0 and run >= 11:
                said.append((18, run - 11, 7))
                at += run
            elif at and run >= 3 and lengths[at] == lengths[at - 1] and lengths[at]:
                k = min(run, 6)
                said.append((16, k - 3, 2))
                at += k
            else:
                said.append((lengths[at], 0, 0))
                at += 1
        flat = {n: 4 if n < 13 else 5 for n in (*range(16), 16, 17, 18)}  # 13 codes of 4 bits and 6 of 5
        code_bits, code = {}, 0
        for n in sorted(flat, key=lambda x: (flat[x], x)):
            code_bits[n] = code if flat[n] == 4 else 2 * 13 + (n - 13)
            code += 1
        self.put(0, 1)
        self.put(15, 4)
        for n in CODE_LENGTH_ORDER:
            self.put(flat[n], 3)
        self.put(0, 1)
        for n, extra, bits in said:
            self.put(reverse(code_bits[n], flat[n]), flat[n])
            self.put(extra, bits)

    def equal_lengths(self, n: int) -> None:
        """A code whose first 2^n symbols have n bits each: all code lengths are n, which takes no bits to say."""
        self.put(0, 1)
        place = CODE_LENGTH_ORDER.index(n)
        self.put(max(0, place - 3), 4)
        for i in range(max(4, place + 1)):
            self.put(int(i == place), 3)
        self.put(1, 1)
        self.put(3, 3)
        self.put((1 << n) - 2, 8)


def encode_bytes(payload: bytes) -> bytes:
    """A container with ``payload``, of a multiple of WIDTH bytes, as an image of green samples with a palette."""
    values = np.frombuffer(payload, np.uint8)
    colours = np.flatnonzero(np.bincount(values, minlength=256))
    w, height = BitWriter(), len(values) // WIDTH
    w.put(0x2F, 8)
    w.put(WIDTH - 1, 14)
    w.put(height - 1, 14)
    w.put(0, 4)
    w.put(0b111, 3)  # a transform: the palette
    w.put(len(colours) - 1, 8)
    w.put(0, 1)  # no cache
    w.equal_lengths(8)  # of green; the palette's differences follow
    for s in (0, 0):
        w.one_symbol(s)
    w.equal_lengths(8)
    w.one_symbol(0)
    before = 0
    for i, c in enumerate(colours.tolist()):
        for v in (c - before, 0 if i else 255):
            w.put(int(f"{v:08b}"[::-1], 2), 8)
        before = c
    w.put(0, 1)  # no further transform
    w.put(0, 2)  # no cache, one group of codes
    place = np.zeros(256, np.uint8)
    place[colours] = np.arange(len(colours))
    index = place[values]
    if shift := palette_shift(len(colours)):
        each = 8 >> shift
        parts = index.reshape(-1, 1 << shift).astype(np.uint16) << (np.arange(1 << shift, dtype=np.uint16) * each)
        index, n = parts.sum(axis=1).astype(np.uint8), 8
    else:
        n = (len(colours) - 1).bit_length()
    w.equal_lengths(n)
    for s in (0, 0, 255, 0):
        w.one_symbol(s)
    flat = np.unpackbits(index[:, None], axis=1)[:, 8 - n :].ravel()
    head = np.unpackbits(np.frombuffer(w.value.to_bytes(w.n // 8 + 1, "little"), np.uint8), bitorder="little")[: w.n]
    data = np.packbits(np.concatenate([head, flat]), bitorder="little").tobytes()
    return container(data)


# --- many images in step -----------------------------------------------------------------------------------


class Plain:
    """The codes of images with one group of codes, no transform and no cache; ``bits`` is the length of what says them."""

    def __init__(self, bits: int, green: Code, distance: Code):
        self.bits, self.green, self.distance = bits, green.table(), distance.table()


_SEEN: dict[int, dict[int, Plain]] = {}  # by the number of bits that say the codes, and by these bits


def plain_codes(stream: bytes) -> Plain | None:
    """The codes of a stream that can be read in step; streams that say their codes alike share them."""
    head = int.from_bytes(stream[5:261], "little")
    for bits, known in _SEEN.items():
        if (found := known.get(head & (1 << bits) - 1)) is not None:
            return found
    if stream[:1] != b"\x2f" or stream[4] >> 5 or head & 0b111:  # a version, a transform, a cache or several groups
        return None
    bits = Bits(stream)
    bits.at = 43
    green, red, blue, alpha, distance = (read_code(bits, n) for n in (LITERALS + LENGTH_CODES, 256, 256, 256, DISTANCE_CODES))
    found = Plain(bits.at - 40, green, distance)
    if red.single is None or blue.single is None or alpha.single is None or found.green is None or found.distance is None or found.bits > 2048:
        return None
    if sum(map(len, _SEEN.values())) < 256:
        _SEEN.setdefault(found.bits, {})[head & (1 << found.bits) - 1] = found
    return found


def _prefixed(window: np.ndarray, prefix: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Value and number of extra bits of length or distance prefixes, from the bits that follow."""
    n = np.maximum(prefix - 2, 0) >> 1
    return np.where(prefix < 4, prefix + 1, ((2 + (prefix & 1)) << n) + (window & (1 << n) - 1) + 1), n


def greens_in_step(streams: list[bytes], codes: list[Plain]) -> list[np.ndarray]:
    """Green samples of each stream's image."""
    size = np.array([len(x) for x in streams])
    raw = np.frombuffer(b"".join(streams) + b"\0" * 8, np.uint8).astype(np.uint32)
    window = raw[:-3] | raw[1:-2] << np.uint32(8) | raw[2:-1] << np.uint32(16) | raw[3:] << np.uint32(24)
    del raw
    first = np.cumsum(size) - size
    head = window[first + 1].astype(np.int64)
    wide, high = (head & 0x3FFF) + 1, (head >> 14 & 0x3FFF) + 1
    total = wide * high
    own = {id(c): c for c in codes}
    place = {k: i for i, k in enumerate(own)}
    green, distance = (np.concatenate([getattr(c, name) for c in own.values()]) for name in ("green", "distance"))
    base = np.array([place[id(c)] for c in codes]) << TABLE_BITS
    at, end = 8 * first + 40 + np.array([c.bits for c in codes]), 8 * (first + size)
    out = np.zeros(int(total.sum()), np.uint8)
    stop = np.cumsum(total)
    start = stop - total
    to, near = start.copy(), np.array(near_offsets())
    mask, lanes = np.uint32((1 << TABLE_BITS) - 1), np.arange(len(streams))
    copies: list[tuple[np.ndarray, ...]] = []
    look = lambda p: window[np.minimum(p >> 3, len(window) - 1)] >> (p & 7).astype(np.uint32)
    while len(lanes):
        found = green[base + (look(at) & mask)]
        s = found >> 4
        at += found & 15
        c = np.flatnonzero(s >= LITERALS)
        if len(c):
            n, bits = _prefixed(look(at[c]).astype(np.int64), s[c].astype(np.int64) - LITERALS)
            p = at[c] + bits
            found = distance[base[c] + (look(p) & mask)]
            p += found & 15
            d, bits = _prefixed(look(p).astype(np.int64), (found >> 4).astype(np.int64))
            at[c] = p + bits
            by_place = near[np.minimum(d, 120) - 1]
            d = np.where(d <= 120, np.maximum(1, by_place[:, 0] + by_place[:, 1] * wide[c]), d - 120)
            if (d > to[c] - start[c]).any() or (to[c] + n > stop[c]).any():
                raise ValueError("a back-reference leaves the image")
            copies.append((to[c], n, d))
            out[to] = s
            to += 1
            to[c] += n - 1
        else:
            out[to] = s
            to += 1
        open_ = to < stop
        if not open_.all():
            if (at > end).any():
                raise ValueError("the image's bits end too early")
            lanes, at, to, base, stop, start, wide, end = (x[open_] for x in (lanes, at, to, base, stop, start, wide, end))
    if copies:
        o, n, d = (np.concatenate(x) for x in zip(*copies))
        copied = np.repeat(o - np.cumsum(n) + n, n) + np.arange(n.sum())
        source = np.arange(len(out))
        follow = copied - np.repeat(d, n)
        while True:  # where a sample comes from, and where that comes from, ...
            source[copied] = follow
            further = source[follow]
            if np.array_equal(further, follow):
                break
            follow = further
        out[copied] = out[follow]
    return np.split(out, np.cumsum(total)[:-1])


def in_lots(items: list, size: Callable[[object], int]) -> Iterator[list]:
    """The items in lists of about AT_ONCE in size, so that what a task holds doesn't follow its rows."""
    lot, held = [], 0
    for x in items:
        if lot and held + size(x) > AT_ONCE:
            yield lot
            lot, held = [], 0
        lot.append(x)
        held += size(x)
    if lot:
        yield lot


def decode_payloads(media: list[bytes]) -> list[bytes]:
    """What ``encode_payloads`` stored, of many at once."""
    found: list[list[bytes]] = [[] for _ in media]
    plain: list[tuple[int, int, bytes, Plain]] = []
    for i, m in enumerate(media):
        for stream in containers(m):
            if len(stream) > 5 and (codes := plain_codes(stream)) is not None:
                plain.append((i, len(found[i]), stream, codes))
                found[i].append(b"")
            else:
                found[i].append((decode_vp8l(stream) >> np.uint32(8)).astype(np.uint8).tobytes())
    for some in in_lots(plain, lambda x: 2 * len(x[2])):
        for (i, j, *_), px in zip(some, greens_in_step([x[2] for x in some], [x[3] for x in some])):
            found[i][j] = px.tobytes()
    return [b"".join(x) for x in found]


def decode_payload(media: bytes) -> bytes:
    return decode_payloads([media])[0]


# --- the encoder ---------------------------------------------------------------------------------------------


def lengths_of(weights: dict[int, float], size: int, rare: float) -> list[int]:
    """Lengths of a complete prefix code: symbols with weights by Huffman's rule, all others as leaves of one subtree of weight ``rare``."""
    others = [s for s in range(size) if s not in weights]
    deep = max(1, (len(others) - 1).bit_length())
    heap = [(w, s, [s]) for s, w in weights.items()] + ([(rare, size, [size])] if others else [])
    heapq.heapify(heap)
    lengths = [0] * (size + 1)
    while len(heap) > 1:
        (a, i, x), (b, _, y) = heapq.heappop(heap), heapq.heappop(heap)
        for s in x + y:
            lengths[s] += 1
        heapq.heappush(heap, (a + b, i, x + y))
    short = (1 << deep) - len(others)  # so many leaves are one bit shorter
    for k, s in enumerate(others):
        lengths[s] = lengths[size] + deep - (k < short)
    return lengths[:size]


@lru_cache(1)
def stock_codes() -> list[tuple[list[int], list[int], int, int]]:
    """Code lengths of green and of distances, and the bits that say them (value, number), for prose, for texts beyond ASCII, for names and numbers, and for any bytes."""
    copies = {LITERALS + p: 0.4 for p in range(5, 16)}
    prose = {c: 100 / (i + 4) for i, c in enumerate(FREQUENT)} | {c: 1.2 for c in b".,\n"} | {c: 0.25 for c in b"'-:;?!()0123456789" + FREQUENT[1:16].upper()} | copies
    wide = {c: 6.0 for c in range(0x80, 0xC0)} | {c: 5.0 for c in (*range(0xC3, 0xC6), 0xD0, 0xD1, *range(0xE3, 0xEA))} | {0x20: 40.0} | copies
    names = {c: 3.0 for c in b"abcdefghijklmnopqrstuvwxyz0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZ-_./= \n"} | copies
    found = []
    for weights in (prose, prose | {c: 4.0 for c in range(0x80, 0xC0)} | {c: 30.0 for c in (0xC3, 0xD0, 0xD1)}, wide, names, copies):
        rare = max(2.0, 0.04 * sum(weights.values())) if weights is not copies else 200.0
        green = lengths_of(weights, LITERALS + LENGTH_CODES, rare)
        distance = lengths_of({p: 1.0 for p in range(14, 26)}, DISTANCE_CODES, 1.0)
        w = BitWriter()
        w.put(0, 3)  # no transform, no cache, one group of codes
        w.lengths(green)
        for s in (0, 0, 255):
            w.one_symbol(s)
        w.lengths(distance)
        found.append((green, distance, w.value, w.n))
    return found


@lru_cache(1)
def stock_bits() -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """For each code of the stock and symbol: bits and their number, of green and of distances."""

    def canonical(lengths: list[int]) -> tuple[list[int], list[int]]:
        values, code, before = [0] * len(lengths), 0, 0
        for n, s in sorted((n, s) for s, n in enumerate(lengths) if n):
            code <<= n - before
            values[s] = reverse(code, n)
            code, before = code + 1, n
        return values, lengths

    both = [(canonical(g), canonical(d)) for g, d, *_ in stock_codes()]
    return tuple(np.array([x[i][j] for x in both], np.int64) for i in range(2) for j in range(2))


def repeats_in(values: np.ndarray, image: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(place, length, distance) of repeats, of GRAM bytes or more, of earlier bytes of the same image; they don't overlap."""
    none = np.empty(0, np.int64)
    if len(values) <= GRAM:
        return none, none, none
    h, size = values.astype(np.uint64) + np.uint64(1), 1
    while size < GRAM:
        h = h[:-size] * np.uint64(0x9E3779B97F4A7C15) + h[size:]
        h ^= h >> np.uint64(29)
        size *= 2
    key = np.sort((h & np.uint64(0xFFFFFFFF00000000)) | np.arange(len(h), dtype=np.uint64))
    same = np.flatnonzero(key[1:] >> np.uint64(32) == key[:-1] >> np.uint64(32))
    here, before = ((key[same + k] & np.uint64(0xFFFFFFFF)).astype(np.int64) for k in (1, 0))
    fits = (h[here] == h[before]) & (image[here + GRAM - 1] == image[before])
    distance = np.zeros(len(h), np.int64)
    distance[here[fits]] = (here - before)[fits]
    edge = np.flatnonzero(np.diff(distance, prepend=0))
    ends = np.r_[edge[1:], len(h)]
    some = distance[edge] > 0
    out, free = [], 0
    for a, z, d in zip(edge[some].tolist(), (ends[some] + GRAM - 1).tolist(), distance[edge[some]].tolist()):
        a = max(a, free)
        while z - a >= GRAM:
            n = min(z - a, 4096)
            out.append((a, n, d))
            a += n
            free = a
    place, n, d = np.array(out, np.int64).reshape(-1, 3).T
    if len(place):  # hashes may agree by chance, and a run may reach into the next image
        at = np.repeat(place - np.cumsum(n) + n, n) + np.arange(n.sum())
        wrong = (values[at] != values[at - np.repeat(d, n)]) | (image[at] != image[np.repeat(place - d, n)])
        good = np.add.reduceat(wrong, np.cumsum(n) - n) == 0
        place, n, d = place[good], n[good], d[good]
    return place, n, d


def _prefix_of(value: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Prefix, extra bits and their number for lengths or distances."""
    v = value - 1
    top = np.frexp(np.maximum(v, 1).astype(np.float64))[1] - 1
    n = np.where(v < 4, 0, top - 1)
    return np.where(v < 4, v, 2 * top + (v >> np.maximum(n, 0) & 1)), np.where(v < 4, 0, v & (1 << n) - 1), n


def encode_images(payloads: list[bytes]) -> list[bytes]:
    """A container for each payload, of a multiple of WIDTH bytes and of many different ones."""
    size = np.array([len(p) for p in payloads])
    values, image = np.frombuffer(b"".join(payloads), np.uint8), np.repeat(np.arange(len(payloads)), size)
    place, n, d = repeats_in(values, image)
    symbol, begins = values.astype(np.int64), np.ones(len(values), bool)
    inner = np.repeat(place - np.cumsum(n - 1) + n, n - 1) + np.arange((n - 1).sum())
    begins[inner] = False
    length, extra, extra_n = _prefix_of(n)
    symbol[place] = LITERALS + length
    prefix, more, more_n = _prefix_of(d + 120)
    at = np.flatnonzero(begins)
    symbol, of = symbol[at], image[at]
    used = np.bincount(of * (LITERALS + LENGTH_CODES) + symbol, minlength=len(payloads) * (LITERALS + LENGTH_CODES)).reshape(len(payloads), -1)
    values_g, n_g, values_d, n_d = stock_bits()
    heads = stock_codes()
    code = (used @ n_g.T + np.array([x[3] for x in heads])).argmin(axis=1)
    both = (values_g << 4 | n_g).ravel()[(code * (LITERALS + LENGTH_CODES))[of] + symbol]
    bits, count = both >> 4, both & 15
    # a copy's bits are its length, the distance's prefix and what follows either
    copy, c = np.searchsorted(at, place), code[image[place]]
    bits[copy] |= extra << count[copy]
    count[copy] += extra_n
    bits[copy] |= values_d[c, prefix] << count[copy]
    count[copy] += n_d[c, prefix]
    bits[copy] |= more << count[copy]
    count[copy] += more_n
    begin = np.searchsorted(of, np.arange(len(payloads)))
    ends = np.cumsum(count)
    own = np.diff(np.r_[ends[begin] - count[begin], ends[-1]])
    head_n = np.array([40 + heads[k][3] for k in code])
    words = -(-(head_n + own) // 32)  # an image begins at a word
    first = np.cumsum(words) - words
    to = (32 * first + head_n - ends[begin] + count[begin])[of] + ends - count
    flat = np.zeros(int(words.sum()) + 3, np.int64)
    word, shift = to >> 5, to & 31
    low = bits << shift  # the sign is a bit like any other
    new = np.flatnonzero(np.diff(word, prepend=-1))
    flat[word[new]] += np.add.reduceat(low & 0xFFFFFFFF, new)  # bits don't meet, so sums join them
    flat[word[new] + 1] += np.add.reduceat(low >> 32 & 0xFFFFFFFF, new)
    np.add.at(flat, word[copy] + 2, bits[copy] >> (63 - shift[copy]) >> 1)
    data = flat.astype("<u4").tobytes()
    out = []
    for p, k, a, w, m in zip(payloads, code.tolist(), first.tolist(), words.tolist(), (head_n + own).tolist()):
        _, _, head, bits_ = heads[k]
        front = (0x2F | (WIDTH - 1) << 8 | (len(p) // WIDTH - 1) << 22 | head << 40).to_bytes(4 * (bits_ // 32 + 3), "little")
        body = bytearray(data[4 * a : 4 * (a + w)])
        whole = (40 + bits_) >> 3
        body[:whole], body[whole] = front[:whole], body[whole] | front[whole]
        out.append(container(bytes(body[: -(-m // 8)])))
    return out


def container(data: bytes) -> bytes:
    body = b"WEBPVP8L" + struct.pack("<I", len(data)) + data + b"\0" * (len(data) & 1)
    return b"RIFF" + struct.pack("<I", len(body)) + body


def encode_payloads(payloads: list[bytes]) -> list[bytes]:
    """For each payload, of a multiple of WIDTH bytes, its containers one after another."""
    if any(len(p) % WIDTH for p in payloads):
        raise ValueError(f"a payload is no multiple of {WIDTH} bytes")
    most = WIDTH * ROWS
    parts = [(i, p[at : at + most]) for i, p in enumerate(payloads) for at in range(0, len(p), most)]
    many = [len(set(p)) > 16 for _, p in parts]
    images = (x for some in in_lots([p for (_, p), m in zip(parts, many) if m], len) for x in encode_images(some))
    out: list[list[bytes]] = [[] for _ in payloads]
    for (i, p), m in zip(parts, many):
        out[i].append(next(images) if m else encode_bytes(p))
    return [b"".join(x) for x in out]


def encode_payload(payload: bytes) -> bytes:
    return encode_payloads([payload])[0]
