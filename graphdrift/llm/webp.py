"""Lossless WebP (VP8L): an encoder, a decoder, and byte payloads kept as RGB images.

The decoder reads prefix codes (simple and normal), prefix-code groups, back
references, the colour cache, and inverts the predictor, cross-colour,
subtract-green and palette transforms. Many images are decoded side by side: all
streams of a block advance by one pixel a step, each step a handful of numpy
operations over the streams that are still running, so no Python code runs per
pixel. Parsed prefix-code headers are remembered by their bits.

A payload is cut into strips of at most ``STRIP_ROWS`` rows of 64 RGB pixels (192
bytes); its stored form is the strips' WebP files one after another. Strips of few
colours go through a palette, all others through predictor, cross-colour and green
transforms, whether or not text gains by them: the predictor and the elements that
leave the least are looked for in all strips of a height together. What ordinary text
leaves has one fixed set of code lengths (made from a rule on the size of a
difference), other strips have their own; all have back references and a colour cache.
The choice depends on a strip's bytes alone, so equal texts are stored alike.

Defined results: null text is empty, and an empty text is stored as one row of
spaces; texts of any length become as many strips as they need; repeated rows give
equal values; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import heapq
import struct
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphdrift.llm import common

WIDTH, ROW, STRIP_ROWS = 64, 192, 32
#: A strip of whose differences the usual code would take more bits a byte than this gets its own code.
OWN_CODE_BITS = 8.5
MIN_MATCH, MAX_MATCH = 8, 4096
#: The colour cache of stored strips has 2^CACHE_BITS places.
CACHE_BITS = 6
#: Strips of up to so many colours are stored through a palette, whose indices are then packed.
FEW_COLOURS = 16
#: Strips whose transforms are looked for together.
STRIPS_AT_ONCE = 64
#: One tile covers a strip.
TILE_BITS = 9

# Fixed values of the format: the order in which code-length codes are stored.
CODE_ORDER = [17, 18, 0, 1, 2, 3, 4, 5, 16, 6, 7, 8, 9, 10, 11, 12, 13, 14, 15]
PREDICTOR, CROSS, GREEN, PALETTE = range(4)
CACHE_FACTOR = 0x1E35A7BD


def _near_offsets() -> list[tuple[int, int]]:
    """(x, y) of the 120 short distance codes: the pixels above and left by closeness."""
    spots = [(x, y) for y in range(8) for x in range(-7, 9) if y or x > 0]
    return sorted(spots, key=lambda s: (s[0] ** 2 + s[1] ** 2, abs(s[0]), s[0] < 0))


NEAR = _near_offsets()

# ---------------------------------------------------------------- prefix codes


def code_lengths(counts: list[int], limit: int = 15) -> list[int]:
    """Lengths of a prefix code for the counted symbols, none above ``limit``."""
    used = [i for i, c in enumerate(counts) if c]
    out = [0] * len(counts)
    if len(used) < 2:
        for i in used:
            out[i] = 1
        return out
    weight = {i: counts[i] for i in used}
    while True:
        heap = [(w, i, (i,)) for i, w in weight.items()]
        heapq.heapify(heap)
        depth = dict.fromkeys(used, 0)
        while len(heap) > 1:
            a, ta, xa = heapq.heappop(heap)
            b, tb, xb = heapq.heappop(heap)
            for i in xa + xb:
                depth[i] += 1
            heapq.heappush(heap, (a + b, min(ta, tb), xa + xb))
        if max(depth.values()) <= limit:
            for i, d in depth.items():
                out[i] = d
            return out
        weight = {i: (w >> 1) + 1 for i, w in weight.items()}


def canonical(lengths) -> list[int]:
    """Codes for lengths, bits reversed for writing from the low end."""
    codes, code, last = [0] * len(lengths), 0, 0
    for n, i in sorted([(n, i) for i, n in enumerate(lengths) if n]):
        code <<= n - last
        last = n
        codes[i] = int(format(code, f"0{n}b")[::-1], 2)
        code += 1
    return codes


def lookup(lengths) -> tuple[np.ndarray, int]:
    """Table indexed by the next bits: symbol << 4 | length; and the number of bits."""
    used = [(i, n) for i, n in enumerate(lengths) if n]
    if len(used) <= 1:
        return np.array([used[0][0] << 4 if used else 0], np.int64), 0
    bits = max(n for _, n in used)
    if sum(1 << (bits - n) for _, n in used) != 1 << bits:
        raise ValueError("incomplete prefix code")
    table, codes = np.zeros(1 << bits, np.int64), canonical(lengths)
    for i, n in used:
        table[codes[i] :: 1 << n] = i << 4 | n
    return table, bits


class BitWriter:
    def __init__(self) -> None:
        self.value, self.size = 0, 0

    def put(self, value: int, bits: int) -> None:
        self.value |= value << self.size
        self.size += bits

    def bytes(self) -> bytes:
        return self.value.to_bytes(-(-self.size // 8), "little")


class BitReader:
    def __init__(self, data: bytes, at: int = 0):
        self.data, self.at = data, at

    def peek(self, bits: int) -> int:
        byte = self.at >> 3
        return (int.from_bytes(self.data[byte : byte + (bits + 14) // 8], "little") >> (self.at & 7)) & ((1 << bits) - 1)

    def take(self, bits: int) -> int:
        value = self.peek(bits)
        self.at += bits
        return value

    def symbol(self, code: tuple[np.ndarray, int]) -> int:
        table, bits = code
        entry = int(table[self.peek(bits) if bits else 0])
        self.at += entry & 15
        return entry >> 4


def write_code(out: BitWriter, lengths: list[int]) -> None:
    """Store a prefix code's lengths."""
    used = [i for i, n in enumerate(lengths) if n]
    if len(used) <= 2 and all(i < 256 for i in used):
        used = used or [0]
        wide = used[0] > 1
        out.put(1 | (len(used) - 1) << 1 | wide << 2, 3)
        out.put(used[0], 8 if wide else 1)
        if len(used) == 2:
            out.put(used[1], 8)
        return
    tokens, i = [], 0
    while i < len(lengths):
        run = 1
        while i + run < len(lengths) and lengths[i + run] == lengths[i]:
            run += 1
        n, i = lengths[i], i + run
        if n:
            tokens.append((n, 0, 0))
            run -= 1
        while run:
            if n and run >= 3:
                k = min(run, 6)
                tokens.append((16, k - 3, 2))
            elif not n and run >= 11:
                k = min(run, 138)
                tokens.append((18, k - 11, 7))
            elif not n and run >= 3:
                k = min(run, 10)
                tokens.append((17, k - 3, 3))
            else:
                k = 1
                tokens.append((n, 0, 0))
            run -= k
    counts = [0] * 19
    for t, _, _ in tokens:
        counts[t] += 1
    inner = code_lengths(counts, 7)
    stored = max(4, max(k for k, s in enumerate(CODE_ORDER) if inner[s]) + 1)
    out.put(0, 1)
    out.put(stored - 4, 4)
    for s in CODE_ORDER[:stored]:
        out.put(inner[s], 3)
    out.put(0, 1)
    codes = canonical(inner)
    single = sum(1 for n in inner if n) == 1
    for t, extra, bits in tokens:
        if not single:
            out.put(codes[t], inner[t])
        out.put(extra, bits)


def read_code(bits: BitReader, size: int) -> list[int]:
    """Read a prefix code's lengths."""
    lengths = [0] * size
    if bits.take(1):
        second = bits.take(1)
        lengths[bits.take(8 if bits.take(1) else 1)] = 1
        if second:
            lengths[bits.take(8)] = 1
        return lengths
    inner = [0] * 19
    for s in CODE_ORDER[: 4 + bits.take(4)]:
        inner[s] = bits.take(3)
    left = size
    if bits.take(1):
        left = 2 + bits.take(2 + 2 * bits.take(3))
    code, i, last = lookup(inner), 0, 8
    while i < size and left:
        left -= 1
        s = bits.symbol(code)
        if s < 16:
            lengths[i] = s
            i += 1
            last = s or last
            continue
        n, repeat = (last, 3 + bits.take(2)) if s == 16 else (0, 3 + bits.take(3)) if s == 17 else (0, 11 + bits.take(7))
        lengths[i : i + repeat] = [n] * repeat
        i += repeat
    return lengths[:size]


def prefix_value(value: int) -> tuple[int, int, int]:
    """A length or distance (from 1) as symbol, extra bits' number and content."""
    v = value - 1
    if v < 4:
        return v, 0, 0
    top = v.bit_length() - 1
    half = (v >> (top - 1)) & 1
    return 2 * top + half, top - 1, v & ((1 << (top - 1)) - 1)


def plane_distance(code: int, width: int) -> int:
    if code > 120:
        return code - 120
    x, y = NEAR[code - 1]
    return max(1, x + y * width)


# ---------------------------------------------------------------- transforms (images are uint8 arrays h, w, 4: A R G B)


def _predictions(L, T, TL, TR) -> list:
    """The fourteen predictions for pixels (..., 4), as functions: only those asked for are worked out."""
    L, T, TL, TR = (v.astype(np.int16) for v in (L, T, TL, TR))
    avg = lambda a, b: (a + b) >> 1

    def black() -> np.ndarray:
        out = np.zeros_like(L)
        out[..., 0] = 255
        return out

    def select() -> np.ndarray:
        p = L + T - TL
        return np.where((np.abs(p - L).sum(-1) < np.abs(p - T).sum(-1))[..., None], L, T)

    def half() -> np.ndarray:
        mean = avg(L, T)
        return np.clip(mean + ((mean - TL + (mean < TL)) >> 1), 0, 255)

    return [
        black, lambda: L, lambda: T, lambda: TR, lambda: TL, lambda: avg(avg(L, TR), T), lambda: avg(L, TL), lambda: avg(L, T), lambda: avg(TL, T), lambda: avg(T, TR),
        lambda: avg(avg(L, TL), avg(T, TR)), select, lambda: np.clip(L + T - TL, 0, 255), half, black, black,
    ]


def _neighbours(pixels: np.ndarray, y: np.ndarray, x: np.ndarray) -> tuple:
    """Left, upper, upper-left and upper-right pixels. On the right border the last is the leftmost of the same row."""
    w = pixels.shape[2]
    up, before, last = np.maximum(y - 1, 0), np.maximum(x - 1, 0), x == w - 1
    return pixels[:, y, before], pixels[:, up, x], pixels[:, up, before], pixels[:, np.where(last, y, up), np.where(last, 0, np.minimum(x + 1, w - 1))]


def predictor(images: np.ndarray, modes: np.ndarray, bits: int, invert: bool) -> np.ndarray:
    """Add (invert) or take off predictions of images (n, h, w, 4) under tiles' modes (n, tiles down, tiles across).

    A pixel needs its left, upper-left, upper and upper-right neighbours, so when
    inverting the pixels with x + 2y alike are independent and are worked on
    together, those of all images at once.
    """
    _, h, w, _ = images.shape
    out = images.copy()
    pixels = out if invert else images
    ys, xs = np.divmod(np.arange(h * w), w)
    wave = xs + 2 * ys
    order = np.argsort(wave, kind="stable")
    cuts = np.flatnonzero(np.diff(wave[order])) + 1
    for part in np.split(order, cuts) if invert else [order]:
        y, x = ys[part], xs[part]
        mode = modes[:, y >> bits, x >> bits].astype(np.int64) & 15
        mode = np.where(y == 0, np.where(x == 0, 0, 1), np.where(x == 0, 2, mode))
        ways, p = _predictions(*_neighbours(pixels, y, x)), None
        for m in np.unique(mode).tolist():
            p = ways[m]() if p is None else np.where((mode == m)[..., None], ways[m](), p)
        out[:, y, x] = (images[:, y, x] + (p if invert else -p)) & 255
    return out


def cross_colour(images: np.ndarray, elements: np.ndarray, bits: int, invert: bool) -> np.ndarray:
    """Add or take off what green tells of red and blue, and red of blue; (n, h, w, 4) and (n, tiles down, tiles across, 4)."""
    _, h, w, _ = images.shape
    e = elements[:, np.arange(h)[:, None] >> bits, np.arange(w)[None, :] >> bits].astype(np.int8).astype(np.int32)
    to_blue_from_red, to_blue, to_red = e[..., 1], e[..., 2], e[..., 3]
    out = images.copy()
    green = images[..., 2].astype(np.int8).astype(np.int32)
    red, blue = images[..., 1].astype(np.int32), images[..., 3].astype(np.int32)
    sign = 1 if invert else -1
    new_red = (red + sign * ((to_red * green) >> 5)) & 255
    true_red = (new_red if invert else red).astype(np.uint8).astype(np.int8).astype(np.int32)
    out[..., 1] = new_red
    out[..., 3] = (blue + sign * (((to_blue * green) >> 5) + ((to_blue_from_red * true_red) >> 5))) & 255
    return out


def subtract_green(images: np.ndarray, invert: bool) -> np.ndarray:
    out = images.copy()
    for k in (1, 3):
        out[..., k] = images[..., k] + images[..., 2] if invert else images[..., k] - images[..., 2]
    return out


def _packing(colours: int) -> int:
    return 3 if colours <= 2 else 2 if colours <= 4 else 1 if colours <= 16 else 0


def pack_palette(image: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Palette (n, 4) and the image of packed indices (in green)."""
    h, w = image.shape[:2]
    palette, index = np.unique(image.reshape(-1, 4), axis=0, return_inverse=True)
    if len(palette) > 256:
        raise ValueError("over 256 colours")
    bits = _packing(len(palette))
    index = index.reshape(h, w)
    each, depth = 1 << bits, 8 >> bits
    padded = np.zeros((h, -(-w // each) * each), np.int64)
    padded[:, :w] = index
    green = (padded.reshape(h, -1, each) << (np.arange(each) * depth)).sum(-1)
    out = np.zeros((*green.shape, 4), np.uint8)
    out[..., 0], out[..., 2] = 255, green
    return palette, out


def unpack_palette(image: np.ndarray, palette: np.ndarray, width: int) -> np.ndarray:
    bits = _packing(len(palette))
    each, depth = 1 << bits, 8 >> bits
    index = (image[..., 2][..., None].astype(np.int64) >> (np.arange(each) * depth)) & ((1 << depth) - 1)
    full = np.zeros((256, 4), np.uint8)
    full[: len(palette)] = palette
    return full[index.reshape(image.shape[0], -1)[:, :width]]


# ---------------------------------------------------------------- general encoder


def _tokens(pixels: list[int], width: int, cache_bits: int, matches: bool):
    """Literals ('p', argb), cache hits ('c', index) and copies ('m', length, distance code)."""
    out, seen, cache, i = [], {}, {}, 0
    keep = lambda v: cache.__setitem__(((CACHE_FACTOR * v) & 0xFFFFFFFF) >> (32 - cache_bits), v) if cache_bits else None
    near = {}
    for k in range(120, 0, -1):
        near[plane_distance(k, width)] = k
    while i < len(pixels):
        n, start = 0, seen.get(tuple(pixels[i : i + 4])) if matches else None
        if start is not None:
            while i + n < len(pixels) and n < MAX_MATCH and pixels[start + n] == pixels[i + n]:
                n += 1
        if n >= 4:
            d = i - start
            out.append(("m", n, near.get(d, d + 120)))
        else:
            n = 1
            slot = ((CACHE_FACTOR * pixels[i]) & 0xFFFFFFFF) >> (32 - cache_bits) if cache_bits else 0
            out.append(("c", slot) if cache_bits and cache.get(slot) == pixels[i] else ("p", pixels[i]))
        for k in range(i, i + n):
            seen[tuple(pixels[k : k + 4])] = k
            keep(pixels[k])
        i += n
    return out


def _argb(image: np.ndarray) -> list[int]:
    return (image.astype(np.int64) << np.array([24, 16, 8, 0])).sum(-1).reshape(-1).tolist()


def _write_pixels(out: BitWriter, image: np.ndarray, cache_bits: int = 0, matches: bool = True, group_bits: int = 0, main: bool = False) -> None:
    h, w = image.shape[:2]
    pixels = _argb(image)
    tokens = _tokens(pixels, w, cache_bits, matches)
    out.put(1 if cache_bits else 0, 1)
    if cache_bits:
        out.put(cache_bits, 4)
    groups, group_of = 1, None
    if main:
        out.put(1 if group_bits else 0, 1)
        if group_bits:
            out.put(group_bits - 2, 3)
            gh, gw = -(-h >> group_bits), -(-w >> group_bits)
            ids = np.arange(gh * gw).reshape(gh, gw) % 3
            groups = int(ids.max()) + 1
            entropy = np.zeros((gh, gw, 4), np.uint8)
            entropy[..., 0], entropy[..., 2] = 255, ids
            _write_pixels(out, entropy)
            group_of = ids
    sizes = [280 + (1 << cache_bits if cache_bits else 0), 256, 256, 256, 40]
    counts = [[[0] * n for n in sizes] for _ in range(groups)]
    at, where = 0, []
    for t in tokens:
        g = int(group_of[(at // w) >> group_bits, (at % w) >> group_bits]) if group_of is not None else 0
        where.append(g)
        c = counts[g]
        if t[0] == "p":
            v = t[1]
            for k, s in ((0, (v >> 8) & 255), (1, (v >> 16) & 255), (2, v & 255), (3, v >> 24)):
                c[k][s] += 1
        elif t[0] == "c":
            c[0][280 + t[1]] += 1
        else:
            c[0][256 + prefix_value(t[1])[0]] += 1
            c[4][prefix_value(t[2])[0]] += 1
        at += t[1] if t[0] == "m" else 1
    lengths = [[code_lengths(c) for c in group] for group in counts]
    for group in lengths:
        for code in group:
            write_code(out, code)
    codes = [[canonical(c) for c in group] for group in lengths]

    def put(g: int, k: int, s: int) -> None:
        if sum(1 for n in lengths[g][k] if n) > 1:
            out.put(codes[g][k][s], lengths[g][k][s])

    for g, t in zip(where, tokens):
        if t[0] == "p":
            v = t[1]
            for k, s in ((0, (v >> 8) & 255), (1, (v >> 16) & 255), (2, v & 255), (3, v >> 24)):
                put(g, k, s)
        elif t[0] == "c":
            put(g, 0, 280 + t[1])
        else:
            s, bits, extra = prefix_value(t[1])
            put(g, 0, 256 + s)
            out.put(extra, bits)
            s, bits, extra = prefix_value(t[2])
            put(g, 4, s)
            out.put(extra, bits)


def wrapped(stream: bytes) -> bytes:
    """A VP8L stream as a WebP file."""
    padded = stream + b"\0" * (len(stream) & 1)
    return b"RIFF" + struct.pack("<I", 12 + len(padded)) + b"WEBPVP8L" + struct.pack("<I", len(stream)) + padded


def _write_transforms(out: BitWriter, image: np.ndarray, transforms: tuple) -> np.ndarray:
    """Write the transforms' headers and give the transformed image."""
    for t in transforms:
        out.put(1 | t[0] << 1, 3)
        if t[0] in (PREDICTOR, CROSS):
            out.put(t[1] - 2, 3)
            if t[0] == PREDICTOR:
                data = np.zeros((*t[2].shape, 4), np.uint8)
                data[..., 0], data[..., 2] = 255, t[2]
                _write_pixels(out, data)
                image = predictor(image[None], t[2][None], t[1], False)[0]
            else:
                _write_pixels(out, t[2])
                image = cross_colour(image[None], t[2][None], t[1], False)[0]
        elif t[0] == GREEN:
            image = subtract_green(image, False)
        else:
            palette, image = pack_palette(image)
            out.put(len(palette) - 1, 8)
            steps = palette.copy()
            steps[1:] -= palette[:-1]
            _write_pixels(out, steps[None])
    return image


def encode_image(image: np.ndarray, transforms: tuple = (), cache_bits: int = 0, matches: bool = True, group_bits: int = 0) -> bytes:
    """A WebP file of an ARGB image (h, w, 4). ``transforms``: in order, (PREDICTOR, bits, modes), (CROSS, bits, elements), (GREEN,), (PALETTE,)."""
    h, w = image.shape[:2]
    out = BitWriter()
    out.put(0x2F, 8)
    out.put(w - 1 | (h - 1) << 14 | int((image[..., 0] != 255).any()) << 28, 32)
    image = _write_transforms(out, image, transforms)
    out.put(0, 1)
    _write_pixels(out, image, cache_bits, matches, group_bits, main=True)
    return wrapped(out.bytes())


# ---------------------------------------------------------------- decoder


class Stream:
    """A parsed image: its transforms, codes, and where its pixels' bits begin."""

    __slots__ = ("width", "height", "coded_width", "transforms", "data", "at", "groups", "cache_bits", "group_bits", "group_of")


class Decoder:
    """Decodes WebP files, many at a time."""

    def __init__(self) -> None:
        self.codes: dict[tuple, tuple] = {}  # lengths -> (number in tables, bits, single)
        self.tables: list[np.ndarray] = []
        self.by_base: dict[int, np.ndarray] = {}
        self.bases: list[int] = []
        self.total = 0
        self.headers: dict[int, list] = {}
        self.told: dict[int, dict[int, dict]] = {}  # first bits -> size -> width and bits of transforms and codes -> what they say
        self.kept = 0

    def _code(self, lengths: list[int]) -> tuple[int, int]:
        """(base in the joined table, bits) of a prefix code."""
        key = tuple(lengths)
        if key not in self.codes:
            table, bits = lookup(lengths)
            self.codes[key] = (self.total, bits)
            self.tables.append(table)
            self.by_base[self.total] = table
            self.total += len(table)
        return self.codes[key]

    def _groups(self, bits: BitReader, groups: int, cache_bits: int) -> list[list[tuple[int, int]]]:
        """Prefix codes of all groups; one-group headers met before are known by their first bits."""
        begin = bits.at
        if groups == 1:
            probe = bits.peek(64) << 4 | cache_bits
            for size, content, found in self.headers.get(probe, ()):
                if bits.peek(size) == content:
                    bits.at = begin + size
                    return found
        sizes = [280 + (1 << cache_bits if cache_bits else 0), 256, 256, 256, 40]
        found = [[self._code(read_code(bits, n)) for n in sizes] for _ in range(groups)]
        if groups == 1 and len(self.headers) < 64:
            size = bits.at - begin
            bits.at = begin
            if size >= 64:
                self.headers.setdefault(probe, []).append((size, bits.peek(size), found))
            bits.at = begin + size
        return found

    def _image(self, bits: BitReader, w: int, h: int) -> np.ndarray:
        """An inner image (transform data), decoded at once."""
        s = self._open(bits, w, h, main=False)
        flat, end = self._scalar(s, w, h)
        bits.at = end
        return flat

    def _open(self, bits: BitReader, w: int, h: int, main: bool) -> Stream:
        s = Stream()
        s.coded_width, s.height, s.data = w, h, bits.data
        s.cache_bits = bits.take(4) if bits.take(1) else 0
        s.group_bits, s.group_of, groups = 0, None, 1
        if main and bits.take(1):
            s.group_bits = 2 + bits.take(3)
            ids = self._image(bits, -(-w >> s.group_bits), -(-h >> s.group_bits))
            s.group_of = ids[..., 1].astype(np.int64) << 8 | ids[..., 2]
            groups = int(s.group_of.max()) + 1
        s.groups = self._groups(bits, groups, s.cache_bits)
        s.at = bits.at
        return s

    def _scalar(self, s: Stream, w: int, h: int) -> tuple[np.ndarray, int]:
        """One image, pixel by pixel: for the small inner images, and the standard for the other way."""
        bits, out, cache = BitReader(s.data, s.at), [], {}
        codes = [[(self.by_base[b], n) for b, n in g] for g in s.groups]
        while len(out) < w * h:
            y, x = divmod(len(out), w)
            code = codes[int(s.group_of[y >> s.group_bits, x >> s.group_bits]) if s.group_of is not None else 0]
            v = bits.symbol(code[0])
            begin = len(out)
            if v < 256:
                red, blue, alpha = (bits.symbol(code[k]) for k in (1, 2, 3))
                out.append(alpha << 24 | red << 16 | v << 8 | blue)
            elif v < 280:
                n = self._value(bits, v - 256)
                d = plane_distance(self._value(bits, bits.symbol(code[4])), w)
                for _ in range(n):
                    out.append(out[-d])
            else:
                out.append(cache.get(v - 280, 0))
            if s.cache_bits:
                for p in out[begin:]:
                    cache[((CACHE_FACTOR * p) & 0xFFFFFFFF) >> (32 - s.cache_bits)] = p
        return _channels(np.array(out[: w * h], np.uint32)).reshape(h, w, 4), bits.at

    @staticmethod
    def _value(bits: BitReader, symbol: int) -> int:
        if symbol < 4:
            return symbol + 1
        extra = (symbol - 2) >> 1
        return ((2 + (symbol & 1)) << extra) + bits.take(extra) + 1

    def parse(self, file: bytes) -> Stream:
        """Read a WebP file's headers up to its pixels."""
        if file[:4] != b"RIFF" or file[8:16] != b"WEBPVP8L" or file[20] != 0x2F:
            raise ValueError("not a lossless WebP file")
        bits = BitReader(file, 21 * 8)
        w, h = bits.take(14) + 1, bits.take(14) + 1
        bits.take(1)
        if bits.take(3):
            raise ValueError("unknown version")
        begin, probe = bits.at, bits.peek(64)
        for size, known in self.told.get(probe, {}).items():
            found = known.get((w, bits.peek(size)))
            if found and all(-(-h >> b) == tall for b, tall in found[1]):  # inner images of the same sizes
                s, (transforms, s.groups, s.cache_bits) = Stream(), found[0]
                s.coded_width, s.width, s.height, s.data, s.at = w, w, h, file, begin + size
                s.group_bits, s.group_of, s.transforms = 0, None, transforms
                return s
        transforms, coded = [], w
        while bits.take(1):
            kind = bits.take(2)
            if kind in (PREDICTOR, CROSS):
                b = bits.take(3) + 2
                data = self._image(bits, -(-coded >> b), -(-h >> b))
                transforms.append((kind, b, data[..., 2] if kind == PREDICTOR else data))
            elif kind == GREEN:
                transforms.append((kind,))
            else:
                steps = self._image(bits, bits.take(8) + 1, 1)[0]
                palette = np.cumsum(steps, axis=0, dtype=np.uint8)
                transforms.append((kind, palette, coded))
                coded = -(-coded >> _packing(len(palette)))
        s = self._open(bits, coded, h, main=True)
        s.width, s.transforms = w, transforms
        if transforms and s.group_of is None and coded == w and self.kept < 4096 and all(t[0] != PALETTE for t in transforms):
            self.kept += 1
            size, tall = s.at - begin, [(t[1], -(-h >> t[1])) for t in transforms if t[0] in (PREDICTOR, CROSS)]
            bits.at = begin
            if size >= 64:
                self.told.setdefault(probe, {}).setdefault(size, {})[w, bits.peek(size)] = (transforms, s.groups, s.cache_bits), tall
        return s

    def decode(self, files: list[bytes]) -> list[np.ndarray]:
        """ARGB images (h, w, 4) of WebP files."""
        streams = [self.parse(f) for f in files]
        images = self._side_by_side(streams)
        alike: dict[tuple, list[int]] = {}
        for i, (s, image) in enumerate(zip(streams, images)):
            kinds = tuple((t[0], t[1]) if t[0] in (PREDICTOR, CROSS) else (t[0], i) if t[0] == PALETTE else t for t in s.transforms)
            tiles = [t[2] for t in s.transforms if t[0] in (PREDICTOR, CROSS)]
            if tiles and all(t.shape[:2] == (1, 1) for t in tiles) and PALETTE not in [t[0] for t in s.transforms]:
                # under one tile each, images of one mode are alike whatever their heights
                alike.setdefault((image.shape[1:], kinds, *[int(t[2][0, 0]) for t in s.transforms if t[0] == PREDICTOR]), []).append(i)
            else:
                alike.setdefault((image.shape, kinds), []).append(i)
        for (_, kinds, *_), some in alike.items():  # go through their transforms together, the lower ones filled up
            batch = None
            if kinds:
                batch = np.zeros((len(some), max(images[i].shape[0] for i in some), *images[some[0]].shape[1:]), np.uint8)
                for n, i in enumerate(some):
                    batch[n, : images[i].shape[0]] = images[i]
            for k in range(len(kinds) - 1, -1, -1):
                told = [streams[i].transforms[k] for i in some]
                if kinds[k][0] == PREDICTOR:
                    batch = predictor(batch, np.stack([t[2] for t in told]), told[0][1], True)
                elif kinds[k][0] == CROSS:
                    batch = cross_colour(batch, np.stack([t[2] for t in told]), told[0][1], True)
                elif kinds[k][0] == GREEN:
                    batch = subtract_green(batch, True)
                else:
                    batch = unpack_palette(batch[0], told[0][1], told[0][2])[None]
            for n, i in enumerate(some if kinds else ()):
                images[i] = batch[n][: streams[i].height]
        return images

    def _side_by_side(self, streams: list[Stream]) -> list[np.ndarray]:
        """Entropy-decode all streams in step, one pixel of each at a time."""
        if not streams:
            return []
        sizes = np.array([s.coded_width * s.height for s in streams])
        order = np.argsort(-sizes, kind="stable")
        sizes = sizes[order]
        row = [streams[i] for i in order]
        data = np.frombuffer(b"".join([s.data + b"\0\0\0\0\0\0\0\0" for s in row]), np.uint8)
        words = np.zeros(len(data) - 7, np.uint64)
        for k in range(8):
            words |= data[k : k + len(words)].astype(np.uint64) << np.uint64(8 * k)
        lengths = np.array([len(s.data) + 8 for s in row])
        bitpos = np.array([s.at for s in row]) + 8 * (np.cumsum(lengths) - lengths)
        table = np.concatenate(self.tables)
        codes = np.array([s.groups[0] for s in row], np.int64)  # streams x 5 x (base, bits)
        base, mask = codes[:, :, 0].T.copy(), ((1 << codes[:, :, 1]) - 1).astype(np.uint64).T.copy()
        grouped = [i for i, s in enumerate(row) if s.group_of is not None]
        cached = np.array([s.cache_bits for s in row])
        width = np.array([s.coded_width for s in row])
        caches = np.zeros((len(row), 1 << cached.max()), np.uint32) if cached.any() else None
        alpha_bits = bool(mask[3].any()) or bool(grouped)
        running = np.searchsorted(-sizes, -np.arange(sizes[0]), side="left")  # streams with more than t pixels
        first = np.concatenate([[0], np.cumsum(running)])
        flat = np.zeros(first[-1], np.uint32)
        left, back = np.zeros(len(row), np.int64), np.zeros(len(row), np.int64)
        near_x, near_y = (np.array([0, *[p[k] for p in NEAR]]) for k in (0, 1))
        copying = 0

        def value(idx: np.ndarray, symbol: np.ndarray) -> np.ndarray:
            extra = np.maximum(0, (symbol - 2) >> 1)
            at = bitpos[idx]
            bits = (words[at >> 3] >> (at & 7).astype(np.uint64)).astype(np.int64) & ((1 << extra) - 1)
            bitpos[idx] += extra
            return np.where(symbol < 4, symbol + 1, ((2 + (symbol & 1)) << extra) + bits + 1)

        every = np.arange(len(row))
        for t in range(int(sizes[0])):
            k = running[t]
            for i in grouped:
                if i < k:
                    s = row[i]
                    y, x = divmod(t, s.coded_width)
                    g = s.groups[int(s.group_of[y >> s.group_bits, x >> s.group_bits])]
                    base[:, i] = [c[0] for c in g]
                    mask[:, i] = [(1 << c[1]) - 1 for c in g]
            now = flat[first[t] : first[t + 1]]
            idx = slice(0, k)
            if copying:
                idx = np.flatnonzero(left[:k] == 0)
            at = bitpos[idx]
            if len(at):
                w = words[at >> 3] >> (at & 7).astype(np.uint64)
                e = table[base[0][idx] + (w & mask[0][idx]).astype(np.int64)]
                green, n = e >> 4, e & 15
                literal = green < 256
                if literal.all():
                    sub, r = idx, slice(None)
                else:
                    r = np.flatnonzero(literal)
                    sub = every[idx][r]
                used, w = n[r], w[r] >> n[r].astype(np.uint64)
                e = table[base[1][sub] + (w & mask[1][sub]).astype(np.int64)]
                red, n1 = e >> 4, e & 15
                w = w >> n1.astype(np.uint64)
                e = table[base[2][sub] + (w & mask[2][sub]).astype(np.int64)]
                blue, n2 = e >> 4, e & 15
                step = used + n1 + n2
                if alpha_bits:
                    a = at[r] + step
                    w = words[a >> 3] >> (a & 7).astype(np.uint64)
                    e = table[base[3][sub] + (w & mask[3][sub]).astype(np.int64)]
                    step += e & 15
                else:
                    e = table[base[3][sub]]
                now[sub] = (((e >> 4) << 24) | (red << 16) | (green[r] << 8) | blue).astype(np.uint32)
                bitpos[sub] += step
                if r is not sub and not isinstance(r, slice):
                    q = np.flatnonzero(~literal)
                    other = every[idx][q]
                    bitpos[other] += n[q]
                    hit = green[q] >= 280
                    if hit.any():
                        now[other[hit]] = caches[other[hit], green[q][hit] - 280]
                    m, s = other[~hit], green[q][~hit] - 256
                    if len(m):
                        left[m] = value(m, s)
                        b = bitpos[m]
                        e = table[base[4][m] + ((words[b >> 3] >> (b & 7).astype(np.uint64)) & mask[4][m]).astype(np.int64)]
                        bitpos[m] += e & 15
                        d = value(m, e >> 4)
                        small = np.minimum(d, 120)
                        back[m] = np.where(d > 120, d - 120, np.maximum(1, near_x[small] + near_y[small] * width[m]))
                        copying += len(m)
            if copying:
                c = np.flatnonzero(left[:k] > 0)
                now[c] = flat[first[t - back[c]] + c]
                left[c] -= 1
                copying -= int((left[c] == 0).sum()) + int((left[k:] > 0).sum())
                left[k:] = 0
            if caches is not None:
                c = np.flatnonzero(cached[:k])
                slot = ((now[c].astype(np.uint64) * np.uint64(CACHE_FACTOR)) & np.uint64(0xFFFFFFFF)) >> (32 - cached[c]).astype(np.uint64)
                caches[c, slot.astype(np.int64)] = now[c]
        place = np.concatenate([first[:n] + i for i, n in enumerate(sizes)])
        pixels = _channels(flat[place])
        ends = np.cumsum(sizes)
        out: list = [None] * len(row)
        for i, s in enumerate(row):
            out[order[i]] = pixels[ends[i] - sizes[i] : ends[i]].reshape(s.height, s.coded_width, 4)
        return out


def _channels(argb: np.ndarray) -> np.ndarray:
    """Pixels (n, 4) A R G B of packed ones."""
    return argb.astype(">u4").view(np.uint8).reshape(-1, 4)


# ---------------------------------------------------------------- payloads


def _usual_lengths() -> list[int]:
    """Code lengths of what transforms leave of ordinary text, from a rule: the smaller a difference, the commoner."""
    return code_lengths([9000 // (8 + min(k, 256 - k)) for k in range(256)])


class PayloadEncoder:
    """Strips of payload bytes to WebP files, all strips of a block at once."""

    heads: dict[tuple, tuple] = {}  # mode and elements -> head with the usual codes; for all encoders of a process

    def __init__(self) -> None:
        self.usual = _usual_lengths()
        self.cost = np.array(self.usual, np.float64)

    @staticmethod
    def _head(byte_lengths: list[int], bits: BitWriter | None = None, alpha: int = 255) -> tuple:
        """The bits from the transforms (as written so far) to the codes, and the codes of bytes, copies, cache places and distances."""
        copies = [0] * 24
        least = prefix_value(MIN_MATCH)[0]
        copies[least:] = [7 + (k > 8) * 2 for k in range(24 - least)]
        # room for copies: byte codes grow by one bit, copies share the other half of the code space
        green = [n + 1 if n else 0 for n in byte_lengths]
        counts = [1 << (15 - n) if n else 0 for n in green] + [1 << (12 - c // 2) if c else 0 for c in copies] + [80] * (1 << CACHE_BITS)
        green = code_lengths(counts)
        distance = code_lengths([1 << min(k // 3, 12) for k in range(40)])
        bits = bits or BitWriter()
        bits.put(0, 1)  # no further transform
        bits.put(1, 1)
        bits.put(CACHE_BITS, 4)
        bits.put(0, 1)  # one group
        for code in (green, byte_lengths, byte_lengths):
            write_code(bits, code)
        write_code(bits, [int(k == alpha) for k in range(256)])
        write_code(bits, distance)
        arrays = [(np.array(canonical(c), np.uint64), np.array(c, np.int64)) for c in (green, byte_lengths, distance)]
        if sum(1 for n in byte_lengths if n) == 1:
            arrays[1][1][:] = 0
        chunks = [((bits.value >> k) & 0xFFFFFFFF, min(32, bits.size - k)) for k in range(0, bits.size, 32)]
        return (np.array([c for c, _ in chunks], np.uint64), np.array([n for _, n in chunks], np.int64), arrays, alpha)

    def encode(self, strips: list[bytes]) -> list[bytes]:
        """One WebP file a strip; a strip's length is a multiple of 192."""
        out: list = [None] * len(strips)
        if not strips:
            return out
        # a strip's choice depends on its own bytes alone
        by_size: dict[int, list[int]] = {}
        for i, s in enumerate(strips):
            if self._few(s):
                out[i] = encode_image(self._image(s), ((PALETTE,),))
            else:
                by_size.setdefault(len(s), []).append(i)
        usual: list[tuple[int, bytes, tuple]] = []
        for some in by_size.values():
            for x in range(0, len(some), STRIPS_AT_ONCE):
                now = some[x : x + STRIPS_AT_ONCE]
                for i, rest, way in zip(now, *self._transformed(np.stack([self._image(strips[i]) for i in now]))):
                    left = np.frombuffer(rest, np.uint8)
                    if self.cost[left].mean() <= OWN_CODE_BITS:
                        usual.append((i, rest, way))
                    else:
                        own = code_lengths(np.bincount(left, minlength=256).tolist(), 14)
                        out[i] = self._block([rest], [self._head(own, self._told(way), alpha=0)])[0]
        for i, f in zip([u[0] for u in usual], self._block([u[1] for u in usual], [self._usual_head(u[2]) for u in usual])):
            out[i] = f
        return out

    @staticmethod
    def _few(strip: bytes) -> bool:
        """Has the strip at most FEW_COLOURS colours? Its first pixels answer for most."""
        first = {strip[k : k + 3] for k in range(0, min(len(strip), 192), 3)}
        return len(first) <= FEW_COLOURS and len({strip[k : k + 3] for k in range(0, len(strip), 3)}) <= FEW_COLOURS

    @staticmethod
    def _image(strip: bytes) -> np.ndarray:
        image = np.full((len(strip) // ROW, WIDTH, 4), 255, np.uint8)
        image[..., 1:] = np.frombuffer(strip, np.uint8).reshape(-1, WIDTH, 3)
        return image

    @staticmethod
    def _told(way: tuple) -> BitWriter:
        """The headers of the transforms with that mode and those elements."""
        bits = BitWriter()
        image = np.zeros((1, 1, 4), np.uint8)
        _write_transforms(bits, image, ((PREDICTOR, TILE_BITS, np.full((1, 1), way[0], np.uint8)), (CROSS, TILE_BITS, np.array(way[1:], np.uint8).reshape(1, 1, 4)), (GREEN,)))
        return bits

    def _usual_head(self, way: tuple) -> tuple:
        if way not in self.heads:
            self.heads[way] = self._head(self.usual, self._told(way), alpha=0)
        return self.heads[way]

    @staticmethod
    def _transformed(images: np.ndarray) -> tuple[list[bytes], list[tuple]]:
        """What the predictor and the cross-colour elements that leave the least (and green) leave of images of one height, and each one's mode and elements."""
        size = lambda x: np.abs(x.astype(np.int8).astype(np.int16)).reshape(len(images), -1).sum(axis=1, dtype=np.int64)
        ys, xs = np.divmod(np.arange(images.shape[1] * WIDTH), WIDTH)
        ways, own = _predictions(*_neighbours(images, ys, xs)), images.reshape(len(images), -1, 4).astype(np.int16)
        own = own[..., 1:]  # opacity is the same everywhere
        mode = np.argmin([size(own - way()[..., 1:]) for way in ways[:14]], axis=0).astype(np.uint8)
        rest = images.copy()
        for m in np.unique(mode).tolist():
            at = np.flatnonzero(mode == m)
            rest[at] = predictor(images[at], np.full((len(at), 1, 1), m, np.uint8), TILE_BITS, False)
        elements = np.zeros((len(images), 1, 1, 4), np.uint8)
        elements[..., 0] = 255
        values = np.array([0, 8, -8, 16, -16])
        red, green, blue = (rest[..., c].astype(np.int8).astype(np.int16).reshape(len(images), -1) for c in (1, 2, 3))
        for k, told, by in ((3, red, green), (2, blue, green), (1, blue, red)):  # what an element changes, and by what
            given = [(int(v) * by) >> 5 for v in values]
            best = np.argmin([size(told - g) for g in given], axis=0)
            elements[:, 0, 0, k] = values[best].astype(np.uint8)
            if k == 2:
                blue -= np.choose(best[:, None], given)
        rest = subtract_green(cross_colour(rest, elements, TILE_BITS, False), False)[..., 1:]
        return [r.tobytes() for r in rest], [(m, *e) for m, e in zip(mode.tolist(), elements.reshape(-1, 4).tolist())]

    @staticmethod
    def _matches(pixels: np.ndarray, starts: np.ndarray) -> list[tuple[int, int, int]]:
        """(position, length, distance) of copies inside strips, greedy from the left."""
        n = len(pixels)
        if n < 2 * MIN_MATCH:
            return []
        h = np.zeros(n - MIN_MATCH + 1, np.uint64)
        wide = pixels.astype(np.uint64) + np.uint64(1)
        for k in range(MIN_MATCH):
            h = h * np.uint64(0x9E3779B97F4A7C15) + wide[k : k + len(h)]
        strip = np.searchsorted(starts, np.arange(len(h)), side="right")
        order = np.argsort(h ^ (strip.astype(np.uint64) * np.uint64(0xBF58476D1CE4E5B9)), kind="stable")
        a, b = order[:-1], order[1:]
        same = (h[a] == h[b]) & (strip[a] == strip[b])
        earlier = np.full(len(h), -1)
        earlier[b[same]] = a[same]
        ends = np.append(starts[1:], n)
        out, free = [], 0
        for i in np.flatnonzero(earlier >= 0).tolist():
            if i < free:
                continue
            j, end = int(earlier[i]), int(ends[strip[i] - 1])
            limit = min(MAX_MATCH, end - i)
            differ = np.flatnonzero(pixels[j : j + limit] != pixels[i : i + limit])
            m = int(differ[0]) if len(differ) else limit
            if m >= MIN_MATCH:
                out.append((i, m, i - j))
                free = i + m
        return out

    def _block(self, strips: list[bytes], heads: list[tuple]) -> list[bytes]:
        """WebP files of what is left of strips. Their heads have the same codes."""
        if not strips:
            return []
        _, _, (green, side, far), alpha = heads[0]
        data = np.frombuffer(b"".join(strips), np.uint8).astype(np.int64).reshape(-1, 3)
        sizes = np.array([len(s) // 3 for s in strips])
        starts = np.cumsum(sizes) - sizes
        pixels = data[:, 0] << 16 | data[:, 1] << 8 | data[:, 2]
        r, g, b = data[:, 0], data[:, 1], data[:, 2]
        n1, n2 = green[1][g], side[1][r]
        value = green[0][g] | side[0][r] << n1.astype(np.uint64) | side[0][b] << (n1 + n2).astype(np.uint64)
        bits = n1 + n2 + side[1][b]
        # a place of the cache holds the last pixel of the strip that belongs there
        slot = (((pixels | alpha << 24) * CACHE_FACTOR) & 0xFFFFFFFF) >> (32 - CACHE_BITS)
        place = np.repeat(np.arange(len(strips)), sizes) << CACHE_BITS | slot
        order = np.argsort(place.astype(np.uint16) if len(strips) << CACHE_BITS <= 1 << 16 else place, kind="stable")
        known = (place[order[1:]] == place[order[:-1]]) & (pixels[order[1:]] == pixels[order[:-1]])
        hit = order[1:][known]
        value[hit], bits[hit] = green[0][280 + slot[hit]], green[1][280 + slot[hit]]
        token = np.ones(len(value), bool)
        for i, m, d in self._matches(pixels, starts):
            s, e, x = prefix_value(m)
            s2, e2, x2 = prefix_value(d + 120)
            v, size = int(green[0][256 + s]), int(green[1][256 + s])
            for piece, n in ((x, e), (int(far[0][s2]), int(far[1][s2])), (x2, e2)):
                v |= piece << size
                size += n
            value[i], bits[i] = v, size
            token[i + 1 : i + m] = False
        strip = np.repeat(np.arange(len(strips)), sizes)[token]
        value, bits = value[token], bits[token]
        count = np.bincount(strip, minlength=len(strips))
        # tokens of a strip: two for the size, the head, the pixels
        parts = np.array([len(h[0]) for h in heads])
        lead = 2 + parts
        begin = np.cumsum(count + lead) - count - lead
        all_value, all_bits = np.zeros(len(value) + lead.sum(), np.uint64), np.zeros(len(value) + lead.sum(), np.int64)
        at = np.arange(len(value)) + np.cumsum(lead)[strip]
        all_value[at], all_bits[at] = value, bits
        rows = sizes // WIDTH
        all_value[begin], all_bits[begin] = 0x2F, 8
        all_value[begin + 1] = ((WIDTH - 1) | (rows - 1) << 14).astype(np.uint64)
        all_bits[begin + 1] = 32
        spot = np.arange(parts.sum()) + np.repeat(begin + 2 - (np.cumsum(parts) - parts), parts)
        all_value[spot], all_bits[spot] = np.concatenate([h[0] for h in heads]), np.concatenate([h[1] for h in heads])
        ends = np.cumsum(all_bits)
        offset = ends - all_bits
        base = offset[begin]
        total = np.append(base[1:], ends[-1]) - base
        room = (total + 63) // 64 + 1
        word0 = np.cumsum(room) - room
        owner = np.repeat(np.arange(len(strips)), count + lead)
        bit = offset - base[owner]
        word, shift = word0[owner] + (bit >> 6), (bit & 63).astype(np.uint64)
        out = np.zeros(room.sum(), np.uint64)
        heads = np.flatnonzero(np.diff(word, prepend=-1))
        out[word[heads]] = np.add.reduceat(all_value << shift, heads)
        over = np.where(shift > 0, (all_value >> np.uint64(1)) >> (np.uint64(63) - shift), np.uint64(0))
        out[word[heads] + 1] |= np.add.reduceat(over, heads)
        raw = out.astype("<u8").tobytes()
        return [wrapped(raw[8 * w : 8 * w + (n + 7) // 8]) for w, n in zip(word0.tolist(), total.tolist())]


def padded(text: bytes) -> bytes:
    """The payload of a text: spaces up to a positive multiple of 192."""
    return text + b" " * (-len(text) % ROW if text else ROW)


def strips_of(payload: bytes) -> list[bytes]:
    step = ROW * STRIP_ROWS
    return [payload[k : k + step] for k in range(0, len(payload), step)]


def files_of(media: bytes) -> list[bytes]:
    """The WebP files in a stored form."""
    out, at = [], 0
    while at < len(media):
        size = 8 + int.from_bytes(media[at + 4 : at + 8], "little")
        out.append(media[at : at + size])
        at += size
    return out


def store_payloads(payloads: list[bytes], encoder: PayloadEncoder) -> list[bytes]:
    cut = [strips_of(p) for p in payloads]
    files = iter(encoder.encode([s for c in cut for s in c]))
    return [b"".join([next(files) for _ in c]) for c in cut]


def load_pixels(media: list[bytes], decoder: Decoder) -> list[np.ndarray]:
    """RGB samples (rows, 64, 3) of stored forms."""
    cut = [files_of(m) for m in media]
    images = iter(decoder.decode([f for c in cut for f in c]))
    return [np.concatenate([next(images)[..., 1:] for _ in c]) for c in cut]


def feature_of(pixels: np.ndarray) -> str:
    """Rows, mean sample, and which of 16 bands of rows are brighter than the mean."""
    mean = pixels.mean(axis=(1, 2))
    edges = np.arange(17) * len(mean) // 16
    total = np.concatenate([[0], np.cumsum(mean)])
    bands = (total[np.maximum(edges[1:], edges[:-1] + 1).clip(max=len(mean))] - total[edges[:-1]]) / np.maximum(1, edges[1:] - edges[:-1])
    bright = int("".join("1" if x > mean.mean() else "0" for x in bands), 2)
    return f"{len(pixels)}:{pixels.mean():.3f}:{bright:04x}"


def _blocks(texts: list[bytes], most: int = 1 << 21) -> Iterator[tuple[int, int]]:
    at = 0
    while at < len(texts):
        end, held = at, 0
        while end < len(texts) and (end == at or held + len(texts[end]) <= most):
            held += len(texts[end])
            end += 1
        yield at, end
        at = end


def stored_documents(docs: DataFrame, gather: int = 6 << 20) -> DataFrame:
    """doc_id, n_bytes, media (stored form), payload and feature (both read back from the stored form).

    A task gathers about ``gather`` bytes of text and decodes their images side by side.
    """
    common.tune(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, decoder = PayloadEncoder(), Decoder()
        ids: list = []
        texts: list[bytes] = []

        def flush() -> pa.RecordBatch:
            nonlocal ids, texts, decoder
            media: list[bytes] = []
            for a, b in _blocks(texts):
                media += store_payloads([padded(t) for t in texts[a:b]], encoder)
            pixels = load_pixels(media, decoder)
            if decoder.total > 1 << 21:
                decoder = Decoder()
            columns = [pa.array(ids, pa.int64()), pa.array([len(t) for t in texts], pa.int64()), pa.array(media, pa.binary()), pa.array([p.tobytes() for p in pixels], pa.binary()), pa.array([feature_of(p) for p in pixels])]
            ids, texts = [], []
            return pa.RecordBatch.from_arrays(columns, names=["doc_id", "n_bytes", "media", "payload", "feature"])

        held = 0
        for batch in batches:
            for i, t in zip(batch.column(0).to_pylist(), common.byte_list(batch.column(1))):
                ids.append(i)
                texts.append(t)
                held += len(t)
                if held > gather or len(ids) >= 4000:
                    yield flush()
                    held = 0
        if ids:
            yield flush()

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), common.text_of().alias("text")).mapInArrow(run, "doc_id long, n_bytes long, media binary, payload binary, feature string")


def media_digests(docs: DataFrame) -> DataFrame:
    """The digest columns of the stored documents."""
    size = F.octet_length("payload")
    return stored_documents(docs).select(
        "doc_id",
        "n_bytes",
        size.cast("long").alias("payload_bytes"),
        F.sha2("payload", 256).alias("payload_sha256"),
        F.crc32(F.expr("substring(payload, -16, 16)")).alias("tail_crc32"),
        F.octet_length("media").cast("long").alias("media_bytes"),
        F.sha2("media", 256).alias("media_sha256"),
        "feature",
    )
