"""Lossless WebP in numpy: an encoder for byte payloads and a full decoder to pixel arrays.

The decoder handles prefix codes (simple and normal), several code groups, back-references, the
colour cache and the predictor, cross-colour, subtract-green and palette transforms.  Streams with one
code group and no cache take a vectorised path: code lengths at every bit position are looked up at
once, the literals' positions are found by following pointers, and copies are made between.
"""

from __future__ import annotations

import functools
import struct
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_map, text_of

#: Fixed values of the format: order of the code-length code, the largest side, cache multiplier.
LENGTH_ORDER = (17, 18, 0, 1, 2, 3, 4, 5, 16, 6, 7, 8, 9, 10, 11, 12, 13, 14, 15)
MAX_SIDE = 16384
CACHE_MULTIPLIER = 0x1E35A7BD
PREDICTOR, CROSS_COLOUR, SUBTRACT_GREEN, PALETTE = 0, 1, 2, 3

#: Near distances: offsets ordered by length, then by horizontal size, right before left.
NEAR = sorted(((x, y) for y in range(8) for x in range(-7, 9) if y or x > 0), key=lambda p: (p[0] ** 2 + p[1] ** 2, abs(p[0]), p[0] < 0))


# ---- prefix codes -------------------------------------------------------------------------------


def code_lengths(counts: np.ndarray, limit: int) -> np.ndarray:
    """Huffman code lengths of at most ``limit`` bits; rare symbols are lifted until they fit."""
    used = np.nonzero(counts)[0]
    out = np.zeros(len(counts), np.int64)
    if len(used) < 2:
        out[used] = 1
        return out
    weight = counts[used].astype(np.int64)
    n = len(used)
    while True:
        order = np.argsort(weight, kind="stable")
        leaves, made, parent = [*weight[order].tolist(), 1 << 62], [], [0] * (2 * n - 1)
        i = j = 0  # the lightest two are at the heads of the leaves and of the nodes made so far
        for fresh in range(n, 2 * n - 1):
            total = 0
            for _ in (0, 1):
                if j < len(made) and made[j] < leaves[i]:
                    parent[n + j] = fresh
                    total += made[j]
                    j += 1
                else:
                    parent[i] = fresh
                    total += leaves[i]
                    i += 1
            made.append(total)
        deep = [0] * (2 * n - 1)
        for k in range(2 * n - 3, -1, -1):
            deep[k] = deep[parent[k]] + 1
        if max(deep[:n]) <= limit:
            out[used[order]] = deep[:n]
            return out
        weight = (weight >> 1) | 1


@functools.lru_cache(maxsize=16)
def _reversed(width: int) -> np.ndarray:
    """Each number of ``width`` bits with its bits in the other order."""
    out = np.zeros(1, np.int64)
    for k in range(width):
        out = np.concatenate([out, out | 1 << (width - 1 - k)])
    return out


def canonical(lengths: np.ndarray) -> np.ndarray:
    """Code of each symbol, its bits reversed for a stream that is filled from the low end."""
    return _canonical(lengths.tobytes())


@functools.lru_cache(maxsize=32)
def _canonical(key: bytes) -> np.ndarray:
    lengths = np.frombuffer(key, np.int64)
    codes = np.zeros(len(lengths), np.int64)
    order, size, width = _ordered(lengths)
    if width:
        # codes of full width count up by the room that each symbol takes
        room = np.left_shift(1, width - size)
        codes[order] = _reversed(width)[np.cumsum(room) - room]
    return codes


def _ordered(lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray, int]:
    """The used symbols by length, then number, with their lengths, and the largest length."""
    order = np.argsort(lengths, kind="stable")
    order = order[np.searchsorted(lengths[order], 1) :]
    size = lengths[order]
    return order, size, int(size[-1]) if len(size) else 0


class Prefix:
    """A decoding table: entry ``symbol << 4 | bits`` for each value of the next ``width`` bits."""

    def __init__(self, lengths: np.ndarray):
        used = np.nonzero(lengths)[0]
        if len(used) == 1:
            self.width, self.table = 0, np.array([int(used[0]) << 4], np.int64)
        else:
            order, size, self.width = _ordered(lengths)
            room = np.left_shift(1, self.width - size)
            if not len(used) or int(room.sum()) != 1 << self.width:
                raise ValueError("prefix code is not complete")
            self.table = np.repeat(order << 4 | size, room)[_reversed(self.width)]
        self.plain = self.table.tolist() if self.width <= 8 else None

    def read(self, bits: BitReader) -> int:
        entry = int(self.table[bits.peek(self.width)]) if self.plain is None else self.plain[bits.peek(self.width)]
        bits.at += entry & 15
        return entry >> 4


class BitReader:
    def __init__(self, data: bytes):
        self.data, self.at, self.end = data + bytes(8), 0, len(data) * 8

    def peek(self, n: int) -> int:
        byte = self.at >> 3
        return int.from_bytes(self.data[byte : byte + 8], "little") >> (self.at & 7) & ((1 << n) - 1)

    def slice(self, lo: int, hi: int) -> tuple[int, int]:
        """The bits from lo to hi as a number, and how many they are."""
        value = int.from_bytes(self.data[lo >> 3 : (hi + 7) >> 3], "little") >> (lo & 7)
        return value & ((1 << (hi - lo)) - 1), hi - lo

    def next_is(self, before: tuple[int, int]) -> bool:
        """Skip the next bits if they are these."""
        if self.at + before[1] > self.end or self.slice(self.at, self.at + before[1]) != before:
            return False
        self.at += before[1]
        return True

    def read(self, n: int) -> int:
        if self.at + n > self.end:
            raise ValueError("stream ends early")
        value = self.peek(n)
        self.at += n
        return value


class BitWriter:
    def __init__(self) -> None:
        self.values: list[np.ndarray] = []
        self.sizes: list[np.ndarray] = []

    def put(self, value: int, bits: int) -> None:
        self.many(np.array([value]), np.array([bits]))

    def many(self, values: np.ndarray, bits: np.ndarray) -> None:
        self.values.append(values)
        self.sizes.append(bits)

    def bytes(self) -> bytes:
        """Values of at most 32 bits each, packed from the low end."""
        value, size = np.concatenate(self.values).astype(np.uint64), np.concatenate(self.sizes).astype(np.int64)
        end = np.cumsum(size)
        start = end - size
        total = int(end[-1]) if len(end) else 0
        words = total // 32 + 2
        shifted = value << (start & 31).astype(np.uint64)
        low = np.bincount(start >> 5, (shifted & np.uint64(0xFFFFFFFF)).astype(np.float64), words)
        high = np.bincount((start >> 5) + 1, (shifted >> np.uint64(32)).astype(np.float64), words)
        return (low + high[:words]).astype(np.uint32).astype("<u4").tobytes()[: (total + 7) // 8]


# ---- encoding -----------------------------------------------------------------------------------


def _run_lengths(lengths: np.ndarray) -> list[tuple[int, int, int]]:
    """Code lengths as (symbol, extra value, extra bits), runs folded."""
    out = []
    edges = [0, *(np.nonzero(np.diff(lengths))[0] + 1).tolist(), len(lengths)]
    for v, lo, hi in zip(lengths[edges[:-1]].tolist(), edges, edges[1:]):
        run = hi - lo
        if run < 3:
            out += [(v, 0, 0)] * run
            continue
        if v == 0:
            while run >= 3:
                n = min(run, 138)
                out.append((18, n - 11, 7) if n >= 11 else (17, n - 3, 3))
                run -= n
        else:
            out.append((v, 0, 0))
            run -= 1
            while run >= 3:
                n = min(run, 6)
                out.append((16, n - 3, 2))
                run -= n
        out += [(v, 0, 0)] * run
    return out


def _write_code(w: BitWriter, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Write a prefix code; returns (codes, bits) per symbol, none for a code of one symbol."""
    values, sizes, codes, bits = _code_header(lengths.tobytes())
    w.many(values, sizes)
    return codes, bits


@functools.lru_cache(maxsize=32)
def _code_header(key: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    w, lengths = BitWriter(), np.frombuffer(key, np.int64)
    codes, bits = _put_code(w, lengths)
    return np.concatenate(w.values), np.concatenate(w.sizes), codes, bits


def _put_code(w: BitWriter, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    used = np.nonzero(lengths)[0].tolist() or [0]
    if len(used) <= 2 and used[-1] < 256:
        w.put(1, 1)
        w.put(len(used) - 1, 1)
        w.put(1, 1)
        w.put(used[0], 8)
        bits = np.zeros(len(lengths), np.int64)
        codes = np.zeros(len(lengths), np.int64)
        if len(used) == 2:
            w.put(used[1], 8)
            bits[used] = 1
            codes[used[1]] = 1
        return codes, bits
    runs = _run_lengths(lengths)
    counts = np.bincount([s for s, _, _ in runs], minlength=19)
    inner = code_lengths(counts, 7)
    shown = max(4, max(i for i, s in enumerate(LENGTH_ORDER) if inner[s]) + 1)
    single = int((inner > 0).sum()) == 1
    w.put(0, 1)
    w.put(shown - 4, 4)
    w.many(np.array([inner[s] for s in LENGTH_ORDER[:shown]]), np.full(shown, 3))
    w.put(0, 1)
    codes = canonical(inner)
    values, sizes = [], []
    for s, extra, n in runs:
        values += [codes[s], extra]
        sizes += [0 if single else inner[s], n]
    w.many(np.array(values), np.array(sizes))
    if len(used) == 1:
        return np.zeros(len(lengths), np.int64), np.zeros(len(lengths), np.int64)
    return canonical(lengths), lengths


def prefix_value(value: int) -> tuple[int, int, int]:
    """A length or distance (from 1) as (symbol, extra value, extra bits)."""
    v = value - 1
    if v < 4:
        return v, 0, 0
    top = v.bit_length() - 1
    second = v >> (top - 1) & 1
    n = top - 1
    return 2 * top + second, v - ((2 + second) << n), n


def _cache_slot(argb: int, cache_bits: int) -> int:
    return (CACHE_MULTIPLIER * argb & 0xFFFFFFFF) >> (32 - cache_bits)


def _tokens(argb: list[int], width: int, cache_bits: int) -> list[tuple]:
    """Greedy matches of at least 3 pixels, cache hits and literals."""
    last: dict[tuple, int] = {}
    cache = [None] * (1 << cache_bits) if cache_bits else None
    near = {x + y * width: i + 1 for i, (x, y) in reversed(list(enumerate(NEAR))) if x + y * width > 0}
    out, i = [], 0
    while i < len(argb):
        key = tuple(argb[i : i + 3])
        j = last.get(key) if len(key) == 3 else None
        n = 0
        if j is not None:
            while i + n < len(argb) and n < 4096 and argb[j + n] == argb[i + n]:
                n += 1
        if n >= 3:
            d = i - j
            out.append(("copy", n, near.get(d, d + 120)))
        else:
            n = 1
            slot = _cache_slot(argb[i], cache_bits) if cache_bits else 0
            out.append(("cache", slot) if cache_bits and cache[slot] == argb[i] else ("pixel", argb[i]))
        for p in range(i, i + n):
            last[tuple(argb[p : p + 3])] = p
            if cache_bits:
                cache[_cache_slot(argb[p], cache_bits)] = argb[p]
        i += n
    return out


@functools.lru_cache(maxsize=4)
def _near_codes(width: int) -> dict[int, int]:
    return {x + y * width: i + 1 for i, (x, y) in reversed(list(enumerate(NEAR))) if x + y * width > 0}


def repeats(pixels: np.ndarray, least: int = 24, probe: int = 8) -> list[tuple[int, int, int]]:
    """(place, length, distance) of stretches of at least ``least`` pixels that occur before, without overlap.

    Every stretch of ``probe`` pixels (a power of two) is hashed and paired with its last occurrence before; where neighbours
    have the same distance they are one longer match, which is then compared pixel by pixel.
    """
    n = len(pixels) - probe + 1
    if n < least:
        return []
    value = pixels.astype(np.uint64)
    key, span = value, 1
    while span < probe:  # a hash of twice as many pixels from two of half as many
        key = key[:-span] * np.uint64(0x9E3779B97F4A7C15) + key[span:]
        key ^= key >> np.uint64(29)
        span *= 2
    order = np.argsort(key, kind="stable")
    same = key[order[1:]] == key[order[:-1]]
    if not same.any():
        return []
    distance = np.zeros(n + 1, np.int64)
    distance[order[1:][same]] = (order[1:] - order[:-1])[same]
    edges = np.nonzero(np.diff(distance, prepend=0))[0]
    out, end = [], 0
    for lo, hi in zip(edges.tolist(), edges[1:].tolist()):
        d, size = int(distance[lo]), hi - lo + probe - 1
        start = max(lo, end)
        size -= start - lo
        if d and size >= least and np.array_equal(pixels[start : start + size], pixels[start - d : start - d + size]):
            end = start + size
            out += [(at, min(4096, end - at), d) for at in range(start, end, 4096)]
    return out


def _write_copies(w: BitWriter, argb: np.ndarray, width: int, copies: list[tuple[int, int, int]]) -> None:
    """The codes and pixels of an opaque image some of whose stretches are copies of earlier ones."""
    literal = np.ones(len(argb), bool)
    near = _near_codes(width)
    spans = []
    for at, n, d in copies:
        literal[at : at + n] = False
        spans.append((at, *prefix_value(n), *prefix_value(near.get(d, d + 120))))
    at, length, extra, more, far, far_extra, far_more = np.array(spans, np.int64).T
    place = np.nonzero(literal)[0]
    red, green, blue = (argb[place, c] for c in (1, 2, 3))
    both = code_lengths(np.bincount(red, minlength=256) + np.bincount(blue, minlength=256), 15)
    clear = np.zeros(256, np.int64)
    clear[argb[0, 0]] = 1
    g_code, g_size = _write_code(w, code_lengths(np.bincount(green, minlength=280) + np.bincount(256 + length, minlength=280), 15))
    code, size = _write_code(w, both)
    _write_code(w, both)
    _write_code(w, clear)
    d_code, d_size = _write_code(w, code_lengths(np.bincount(far, minlength=40), 15))
    each = np.zeros(len(argb), np.int64)
    each[place], each[at] = 3, 4
    start = np.cumsum(each) - each
    values, sizes = np.zeros(int(each.sum()), np.int64), np.zeros(int(each.sum()), np.int64)
    for k, (v, n) in enumerate(((g_code[green], g_size[green]), (code[red], size[red]), (code[blue], size[blue]))):
        values[start[place] + k], sizes[start[place] + k] = v, n
    for k, (v, n) in enumerate(((g_code[256 + length], g_size[256 + length]), (extra, more), (d_code[far], d_size[far]), (far_extra, far_more))):
        values[start[at] + k], sizes[start[at] + k] = v, n
    w.many(values, sizes)


def _write_image(w: BitWriter, argb: np.ndarray, width: int, main: bool, matches: bool = False, cache_bits: int = 0, copies: list[tuple[int, int, int]] | None = None) -> None:
    """An entropy-coded image with one code group; argb: rows of (a, r, g, b)."""
    w.put(1 if cache_bits else 0, 1)
    if cache_bits:
        w.put(cache_bits, 4)
    if main:
        w.put(0, 1)
    if copies:
        return _write_copies(w, argb, width, copies)
    greens = 280 + ((1 << cache_bits) if cache_bits else 0)
    if not matches and not cache_bits:
        # red, green and blue share one code: for payloads, the three hold like samples
        shared = code_lengths(np.bincount(argb[:, 1:].ravel(), minlength=256), 15)
        clear = code_lengths(np.bincount(argb[:, 0], minlength=256), 15)
        codes, sizes = _write_code(w, np.concatenate([shared, np.zeros(greens - 256, np.int64)]))
        _write_code(w, shared)
        _write_code(w, shared)
        a_codes, a_sizes = _write_code(w, clear)
        _write_code(w, np.zeros(40, np.int64))
        colour = argb[:, [2, 1, 3]]
        if int((clear > 0).sum()) == 1:
            flat = colour.ravel()
            w.many(codes[flat], sizes[flat])
        else:
            w.many(np.column_stack([codes[colour], a_codes[argb[:, 0]]]).ravel(), np.column_stack([sizes[colour], a_sizes[argb[:, 0]]]).ravel())
        return
    packed = ((argb[:, 0].astype(np.int64) << 24) | (argb[:, 1].astype(np.int64) << 16) | (argb[:, 2].astype(np.int64) << 8) | argb[:, 3]).tolist()
    tokens = _tokens(packed, width, cache_bits) if matches else [("pixel", p) for p in packed]
    counts = [np.zeros(n, np.int64) for n in (greens, 256, 256, 256, 40)]
    for t in tokens:
        if t[0] == "pixel":
            for c, shift in ((0, 8), (1, 16), (2, 0), (3, 24)):
                counts[c][t[1] >> shift & 255] += 1
        elif t[0] == "cache":
            counts[0][280 + t[1]] += 1
        else:
            counts[0][256 + prefix_value(t[1])[0]] += 1
            counts[4][prefix_value(t[2])[0]] += 1
    own = [_write_code(w, code_lengths(c, 15)) for c in counts]
    put = lambda c, s: w.put(int(own[c][0][s]), int(own[c][1][s]))
    for t in tokens:
        if t[0] == "pixel":
            for c, shift in ((0, 8), (1, 16), (2, 0), (3, 24)):
                put(c, t[1] >> shift & 255)
        elif t[0] == "cache":
            put(0, 280 + t[1])
        else:
            for c, base, v in ((0, 256, t[1]), (4, 0, t[2])):
                s, extra, n = prefix_value(v)
                put(c, base + s)
                w.put(extra, n)


def _blocks(side: int, bits: int) -> int:
    return (side + (1 << bits) - 1) >> bits


def encode(rgb: np.ndarray, *, alpha: np.ndarray | None = None, matches: bool = False, cache_bits: int = 0, subtract_green: bool = False, predictor: int | None = None, cross_colour: tuple[int, int, int] | None = None, palette: bool = False, best: bool = False) -> bytes:
    """A lossless WebP file of an image of shape (height, width, 3) of bytes.

    The default writes literals only; the other options turn on one feature of the format each.  ``best``
    looks at the image: a palette where it has at most 16 colours, the predictor "pixel above" where half of
    the pixels equal it, and back-references where stretches that occurred before are an eighth of the pixels.
    """
    height, width = rgb.shape[:2]
    if not (0 < width <= MAX_SIDE and 0 < height <= MAX_SIDE):
        raise ValueError("image side out of range")
    a = np.full((height, width), 255, np.uint8) if alpha is None else alpha
    argb = np.dstack([a, rgb]).astype(np.int64)
    if best:
        packed = argb[..., 1] << 16 | argb[..., 2] << 8 | argb[..., 3]
        palette = len(set(packed[0].tolist())) <= 16 and len(np.unique(packed)) <= 16
        if not palette and height > 2 and 2 * int((packed[1:] == packed[:-1]).sum()) > height * width:
            predictor = 2
    w = BitWriter()
    w.put(0x2F, 8)
    w.put(width - 1, 14)
    w.put(height - 1, 14)
    w.put(0 if alpha is None else 1, 1)
    w.put(0, 3)
    if palette:
        colours, index = np.unique(argb.reshape(-1, 4), axis=0, return_inverse=True)
        if len(colours) > 256:
            raise ValueError("more than 256 colours")
        w.put(1, 1)
        w.put(PALETTE, 2)
        w.put(len(colours) - 1, 8)
        _write_image(w, np.diff(colours, axis=0, prepend=0) & 255, len(colours), False)
        pack = 3 if len(colours) <= 2 else 2 if len(colours) <= 4 else 1 if len(colours) <= 16 else 0
        index = index.reshape(height, width)
        wide = _blocks(width, pack)
        index = np.pad(index, ((0, 0), (0, (wide << pack) - width))).reshape(height, wide, 1 << pack)
        green = (index << (np.arange(1 << pack) * (8 >> pack))).sum(axis=2)
        argb = np.zeros((height, wide, 4), np.int64)
        argb[..., 0], argb[..., 2], width = 255, green, wide
    if subtract_green:
        w.put(1, 1)
        w.put(SUBTRACT_GREEN, 2)
        argb[..., 1] = (argb[..., 1] - argb[..., 2]) & 255
        argb[..., 3] = (argb[..., 3] - argb[..., 2]) & 255
    if cross_colour:
        w.put(1, 1)
        w.put(CROSS_COLOUR, 2)
        w.put(3, 3)
        n = _blocks(width, 5) * _blocks(height, 5)
        g2r, g2b, r2b = cross_colour
        _write_image(w, np.tile(np.array([255, r2b & 255, g2b & 255, g2r & 255]), (n, 1)), _blocks(width, 5), False)
        red = argb[..., 1].copy()
        argb[..., 1] = (red - _delta(g2r, argb[..., 2])) & 255
        argb[..., 3] = (argb[..., 3] - _delta(g2b, argb[..., 2]) - _delta(r2b, red)) & 255
    if predictor is not None:
        w.put(1, 1)
        w.put(PREDICTOR, 2)
        w.put(3, 3)
        n = _blocks(width, 5) * _blocks(height, 5)
        _write_image(w, np.tile(np.array([255, 0, predictor, 0]), (n, 1)), _blocks(width, 5), False)
        if predictor == 2:
            before = np.zeros_like(argb)
            before[1:] = argb[:-1]
            before[0, 1:], before[0, 0] = argb[0, :-1], (255, 0, 0, 0)
            argb = (argb - before) & 255
        else:
            rows = argb.tolist()
            out = [[None] * width for _ in range(height)]
            for y in range(height):
                for x in range(width):
                    p = _predicted(rows, x, y, width, predictor)
                    out[y][x] = [(v - q) & 255 for v, q in zip(rows[y][x], p)]
            argb = np.array(out)
    w.put(0, 1)
    flat, copies = argb.reshape(-1, 4), None
    if best and (flat[:, 0] == flat[0, 0]).all():
        copies = repeats(flat[:, 1] << 16 | flat[:, 2] << 8 | flat[:, 3])
        copies = copies if 8 * sum(c[1] for c in copies) > len(flat) else None
    _write_image(w, flat, width, True, matches, cache_bits, copies)
    body = w.bytes()
    chunk = b"VP8L" + struct.pack("<I", len(body)) + body + b"\0" * (len(body) & 1)
    return b"RIFF" + struct.pack("<I", len(chunk) + 4) + b"WEBP" + chunk


# ---- decoding -----------------------------------------------------------------------------------


def _read_code(bits: BitReader, size: int) -> np.ndarray:
    lengths = np.zeros(size, np.int64)
    if bits.read(1):
        two = bits.read(1)
        lengths[bits.read(8 if bits.read(1) else 1)] = 1
        if two:
            lengths[bits.read(8)] = 1
        return lengths
    inner = np.zeros(19, np.int64)
    for s in LENGTH_ORDER[: bits.read(4) + 4]:
        inner[s] = bits.read(3)
    left = size
    if bits.read(1):
        left = 2 + bits.read(2 + 2 * bits.read(3))
    code, at, previous, place, data = Prefix(inner), 0, 8, bits.at, bits.data
    table, mask, out = code.table.tolist(), (1 << code.width) - 1, [0] * size
    while at < size and left:
        left -= 1
        ahead = int.from_bytes(data[place >> 3 : (place >> 3) + 4], "little") >> (place & 7)
        entry = table[ahead & mask]
        s, used = entry >> 4, entry & 15
        place += used
        if s < 16:
            out[at] = s
            previous = s or previous
            at += 1
            continue
        ahead >>= used
        if s == 16:
            value, n, used = previous, 3 + (ahead & 3), 2
        elif s == 17:
            value, n, used = 0, 3 + (ahead & 7), 3
        else:
            value, n, used = 0, 11 + (ahead & 127), 7
        place += used
        if at + n > size:
            raise ValueError("code lengths run over")
        if value:
            out[at : at + n] = [value] * n
        at += n
    if place > bits.end:
        raise ValueError("stream ends early")
    bits.at = place
    return np.array(out, np.int64)


def _read_group(bits: BitReader, cache_bits: int) -> list[np.ndarray]:
    out, before = [], (0, 0)
    for n in (280 + ((1 << cache_bits) if cache_bits else 0), 256, 256, 256, 40):
        start = bits.at
        if out and len(out[-1]) == n and bits.next_is(before):
            out.append(out[-1])  # written with the very bits of the code before
            continue
        out.append(_read_code(bits, n))
        before = bits.slice(start, bits.at)
    return out


def _stretches(bits: BitReader, lengths: list[np.ndarray], total: int, width: int, window: int = 1 << 16) -> np.ndarray:
    """Pixels of a stream of literals and copies: (a, r, g, b) rows.

    Literals are looked up for all bit positions of a window at once, and their places found by following
    pointers; a copy ends such a chain, is made, and the next chain begins behind it.
    """
    memo: dict[bytes, Prefix] = {}
    codes = []
    for n in lengths[:4]:
        key = n[:256].tobytes() if not n[256:].any() else n.tobytes()
        if key not in memo:
            memo[key] = Prefix(n if n[256:].any() else n[:256])
        codes.append(memo[key])
    copies = bool(lengths[0][256:].any())
    far = Prefix(lengths[4]) if copies and lengths[4].any() else None
    data = np.frombuffer(bits.data, np.uint8)
    out, done, start = np.empty((total, 4), np.uint8), 0, bits.at
    if not any(c.width for c in codes) and not copies:
        out[:] = [codes[3].table[0] >> 4, codes[1].table[0] >> 4, codes[0].table[0] >> 4, codes[2].table[0] >> 4]
        return out
    while done < total:
        first = start >> 3
        raw = np.zeros(min(window + 16, len(data) - first) + 2, np.uint32)
        raw[:-2] = data[first : first + window + 16]
        words = raw[:-2] | raw[1:-1] << np.uint32(8) | raw[2:] << np.uint32(16)
        peek = (words[:, None] >> np.arange(8, dtype=np.uint32)).ravel()
        size = len(peek)
        looked: dict[int, tuple[np.ndarray, np.ndarray]] = {}
        step = np.arange(size, dtype=np.int32)
        steps = [step]
        for c in codes:
            if c.width and id(c) not in looked:
                entry = np.zeros(size + 64, np.int32)  # past the end nothing moves
                entry[:size] = c.table.astype(np.int32)[peek & np.uint32((1 << c.width) - 1)]
                looked[id(c)] = entry, entry & 15
            step = step + looked[id(c)][1][step] if c.width else step
            steps.append(step)
        if copies:
            if codes[0].width:
                steps[4] = np.where(looked[id(codes[0])][0][:size] >= 256 << 4, -1, steps[4])
            elif codes[0].table[0] >= 256 << 4:
                steps[4] = np.full(size, -1, np.int32)
        jump = memoryview(steps[4])
        at, before = start & 7, done
        stop = size - 64 if first + window + 16 < len(data) else size
        while done < total and 0 <= at < stop:
            chain, room = [], total - done
            push = chain.append
            while room and 0 <= at < stop:
                push(at)
                at = jump[at]
                room -= 1
            copy = chain.pop() if at < 0 else None
            found = np.array(chain, np.int64)
            for column, c, s in zip((2, 1, 3, 0), codes, steps):
                out[done : done + len(found), column] = looked[id(c)][0][s[found]] >> 4 if c.width else c.table[0] >> 4
            done += len(found)
            if copy is not None:
                bits.at = first * 8 + copy
                n, d = _copy(bits, codes[0].read(bits) - 256, far, width)
                if d > done or done + n > total:
                    raise ValueError("copy reaches outside the image")
                source = out[done - d : min(done, done - d + n)]
                out[done : done + n] = source if len(source) == n else np.resize(source, (n, 4))
                done += n
                at = bits.at - first * 8
        start = first * 8 + at
        if done == before or start > bits.end:
            raise ValueError("stream ends early")
    bits.at = start
    return out


def _extra(bits: BitReader, s: int) -> int:
    if s < 4:
        return s + 1
    n = (s - 2) >> 1
    return ((2 + (s & 1)) << n) + bits.read(n) + 1


def _copy(bits: BitReader, s: int, far: Prefix | None, width: int) -> tuple[int, int]:
    """(length, distance) of the copy whose length symbol was read."""
    n = _extra(bits, s)
    if far is None:
        raise ValueError("copy without distances")
    d = _extra(bits, far.read(bits))
    if d > 120:
        return n, d - 120
    x, y = NEAR[d - 1]
    return n, max(1, x + y * width)


def _read_image(bits: BitReader, width: int, height: int, main: bool) -> np.ndarray:
    cache_bits = bits.read(4) if bits.read(1) else 0
    groups, which, block = 1, None, 0
    if main and bits.read(1):
        block = bits.read(3) + 2
        meta = _read_image(bits, _blocks(width, block), _blocks(height, block), False)
        which = (meta[:, 1].astype(np.int64) << 8 | meta[:, 2]).tolist()
        groups = max(which) + 1
    lengths = [_read_group(bits, cache_bits) for _ in range(groups)]
    total = width * height
    if groups == 1 and not cache_bits:
        return _stretches(bits, lengths[0], total, width)
    codes = [[Prefix(n) if n.any() else None for n in g] for g in lengths]
    cache = [0] * (1 << cache_bits) if cache_bits else None
    out: list[int] = []
    wide = _blocks(width, block)
    seen = 0  # pixels that have entered the cache

    while len(out) < total:
        at = len(out)
        group = codes[which[(at // width >> block) * wide + (at % width >> block)] if which else 0]
        s = group[0].read(bits)
        if s < 256:
            r, b, a = group[1].read(bits), group[2].read(bits), group[3].read(bits)
            out.append(a << 24 | r << 16 | s << 8 | b)
        elif s < 280:
            n, d = _copy(bits, s - 256, group[4], width)
            if d > at or at + n > total:
                raise ValueError("copy reaches outside the image")
            for _ in range(n):
                out.append(out[-d])
        else:
            if cache:
                for p in out[seen:]:
                    cache[_cache_slot(p, cache_bits)] = p
                seen = at
            out.append(cache[s - 280])
        if cache and s < 280:
            for p in out[seen:]:
                cache[_cache_slot(p, cache_bits)] = p
            seen = len(out)
        if bits.at > bits.end:
            raise ValueError("stream ends early")
    packed = np.array(out, np.int64)
    return np.stack([packed >> 24 & 255, packed >> 16 & 255, packed >> 8 & 255, packed & 255], axis=1).astype(np.uint8)


def _delta(factor: int, channel: np.ndarray) -> np.ndarray:
    signed = lambda v: (v & 255) - ((v & 128) << 1)
    return (signed(factor) * signed(channel)) >> 5


def _predicted(rows: list, x: int, y: int, width: int, mode: int) -> list[int]:
    """The prediction for one pixel from the pixels before it."""
    if y == 0:
        return [255, 0, 0, 0] if x == 0 else rows[0][x - 1]
    up = rows[y - 1]
    if x == 0:
        return up[0]
    if mode == 0 or mode > 13:
        return [255, 0, 0, 0]
    left, top, corner = rows[y][x - 1], up[x], up[x - 1]
    right = up[x + 1] if x + 1 < width else rows[y][0]
    half = lambda p, q: [(a + b) >> 1 for a, b in zip(p, q)]
    if mode <= 4:
        return (left, top, right, corner)[mode - 1]
    if mode == 5:
        return half(half(left, right), top)
    if mode <= 9:
        return half(*((left, corner), (left, top), (corner, top), (top, right))[mode - 6])
    if mode == 10:
        return half(half(left, corner), half(top, right))
    if mode == 11:
        to_left = sum(abs(t - c) for t, c in zip(top, corner))
        to_top = sum(abs(a - c) for a, c in zip(left, corner))
        return left if to_left < to_top else top
    if mode == 12:
        return [min(255, max(0, a + t - c)) for a, t, c in zip(left, top, corner)]
    return [min(255, max(0, m + int((m - c) / 2))) for m, c in zip(half(left, top), corner)]


def decode(data: bytes) -> np.ndarray:
    """Pixels (height, width, 4) as red, green, blue, alpha; raises ValueError on a broken file."""
    if data[:4] != b"RIFF" or data[8:12] != b"WEBP":
        raise ValueError("not a WebP file")
    at, body = 12, None
    while at + 8 <= len(data):
        kind, size = data[at : at + 4], struct.unpack("<I", data[at + 4 : at + 8])[0]
        if kind == b"VP8L":
            body = data[at + 8 : at + 8 + size]
            break
        at += 8 + size + (size & 1)
    if body is None:
        raise ValueError("no lossless image")
    bits = BitReader(body)
    if bits.read(8) != 0x2F:
        raise ValueError("wrong signature")
    width, height = bits.read(14) + 1, bits.read(14) + 1
    bits.read(1)
    if bits.read(3):
        raise ValueError("unknown version")
    todo, wide = [], width
    while bits.read(1):
        kind = bits.read(2)
        if any(kind == k for k, *_ in todo):
            raise ValueError("a transform occurs twice")
        if kind in (PREDICTOR, CROSS_COLOUR):
            block = bits.read(3) + 2
            todo.append((kind, wide, block, _read_image(bits, _blocks(wide, block), _blocks(height, block), False)))
        elif kind == PALETTE:
            n = bits.read(8) + 1
            colours = np.cumsum(_read_image(bits, n, 1, False).astype(np.int64), axis=0) & 255
            pack = 3 if n <= 2 else 2 if n <= 4 else 1 if n <= 16 else 0
            todo.append((kind, wide, pack, colours))
            wide = _blocks(wide, pack)
        else:
            todo.append((kind, wide, 0, None))
    image = _read_image(bits, wide, height, True).reshape(height, wide, 4)
    for kind, wide, size, table in reversed(todo):
        image = _undo(kind, image, wide, height, size, table)
    return image[..., [1, 2, 3, 0]]


def _undo(kind: int, image: np.ndarray, width: int, height: int, size: int, table: np.ndarray | None) -> np.ndarray:
    if kind == SUBTRACT_GREEN:
        image = image.copy()
        image[..., 1] += image[..., 2]
        image[..., 3] += image[..., 2]
        return image
    if kind == PALETTE:
        each, mask = 8 >> size, (1 << (8 >> size)) - 1
        index = (image[..., 2:3].astype(np.int64) >> (np.arange(1 << size) * each)) & mask
        index = index.reshape(height, -1)[:, :width]
        colours = np.zeros((256, 4), np.uint8)
        colours[: len(table)] = table
        return colours[index]
    wide = _blocks(width, size)
    row, column = np.arange(height)[:, None] >> size, np.arange(width)[None, :] >> size
    element = table.astype(np.int64)[row * wide + column]
    if kind == CROSS_COLOUR:
        v = image.astype(np.int64)
        red = (v[..., 1] + _delta_each(element[..., 3], v[..., 2])) & 255
        blue = (v[..., 3] + _delta_each(element[..., 2], v[..., 2]) + _delta_each(element[..., 1], red)) & 255
        return np.stack([v[..., 0], red, v[..., 2], blue], axis=-1).astype(np.uint8)
    if (element[..., 2] == 2).all():  # the pixel above everywhere: running sums
        image = image.copy()
        image[0, 0, 0] += 255
        image[0] = np.cumsum(image[0], axis=0, dtype=np.uint8)
        return np.cumsum(image, axis=0, dtype=np.uint8)
    modes, rows = element[..., 2].tolist(), image.tolist()
    for y in range(height):
        for x in range(width):
            rows[y][x] = [(v + p) & 255 for v, p in zip(rows[y][x], _predicted(rows, x, y, width, modes[y][x]))]
    return np.array(rows, np.uint8)


def _delta_each(factor: np.ndarray, channel: np.ndarray) -> np.ndarray:
    signed = lambda v: v - ((v & 128) << 1)
    return (signed(factor) * signed(channel)) >> 5


# ---- the operator -------------------------------------------------------------------------------

UNIT = 576
ROW_PIXELS = UNIT // 3


def padded(raw: bytes) -> bytes:
    """Bytes 255 appended up to a positive multiple of 576."""
    return raw + b"\xff" * (max(UNIT, -(-len(raw) // UNIT) * UNIT) - len(raw))


def store(payload: bytes) -> bytes:
    """The payload as one or more files of red, green and blue samples, 192 pixels a row, one after another."""
    samples = np.frombuffer(payload, np.uint8).reshape(-1, ROW_PIXELS, 3)
    return b"".join(encode(samples[i : i + MAX_SIDE], best=True) for i in range(0, len(samples), MAX_SIDE))


def load(media: bytes) -> np.ndarray:
    """All rows of the stored files, (height, 192, 3)."""
    parts, at = [], 0
    while at < len(media):
        size = 8 + struct.unpack("<I", media[at + 4 : at + 8])[0]
        parts.append(decode(media[at : at + size])[..., :3])
        at += size
    return np.concatenate(parts)


def describe(pixels: np.ndarray) -> str:
    """Means of the channels in thousandths, entropy of the samples in thousandths of a bit, and a 64-bit
    hash of which of 8 x 8 cells are brighter than the median cell."""
    means = [int(s) * 1000 // (pixels.shape[0] * pixels.shape[1]) for s in pixels.sum(axis=(0, 1), dtype=np.int64)]
    share = np.bincount(pixels.ravel(), minlength=256) / pixels.size
    share = share[share > 0]
    entropy = int(round(float(-(share * np.log2(share)).sum()) * 1000))
    grey = pixels.sum(axis=2, dtype=np.int64)
    rows = np.arange(8) * grey.shape[0] // 8
    across = np.add.reduceat(grey, np.arange(8) * grey.shape[1] // 8, axis=1)
    heights = np.maximum(1, np.diff(np.append(rows, grey.shape[0])))
    cells = np.add.reduceat(across, rows, axis=0) / heights[:, None]
    bright = (cells > np.median(cells)).ravel()
    return f"rgb={means[0]},{means[1]},{means[2]};entropy={entropy};hash={int(''.join('1' if b else '0' for b in bright), 2):016x}"


MEDIA = "doc_id bigint, n_bytes bigint, media binary, height int, width int, pixels binary, feature string"


def media_column(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Store each whole text as lossless WebP, read the stored bytes back to pixels and describe these.

    Columns: ``doc_id, n_bytes, media`` (the stored files), ``height, width, pixels`` (the decoded samples, row by
    row) and ``feature``.  Null texts count as empty and give one row of samples 255; null ids stay null; equal
    texts give equal values; texts of more than 16384 rows go to several files, one after another; repeated
    rows give repeated rows; an empty table gives an empty table; other columns are ignored.  A map
    without shuffle.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = (pa.int64(), pa.binary(), pa.int32(), pa.int32(), pa.binary(), pa.string())
        names = [c.split()[0] for c in MEDIA.split(", ")]
        for batch in batches:
            rows: list[tuple] = []
            for text in batch.column(1).to_pylist():
                raw = text.encode("utf-8", "surrogatepass")
                media = store(padded(raw))
                pixels = load(media)
                rows.append((len(raw), media, pixels.shape[0], pixels.shape[1], pixels.tobytes(), describe(pixels)))
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array([r[i] for r in rows], t) for i, t in enumerate(kinds))], names)

    return arrow_map(df.select(F.col(id_col).cast("bigint").alias("doc_id"), text_of(text_col).alias("text")), run, MEDIA)


def media_digests(media: DataFrame) -> DataFrame:
    """Sizes and digests of the pixel arrays and of the stored files, one row for each of :func:`media_column`."""
    return media.select(
        "doc_id",
        "n_bytes",
        F.octet_length("pixels").cast("bigint").alias("payload_bytes"),
        F.sha2("pixels", 256).alias("payload_sha256"),
        F.crc32(F.substring("pixels", -32, 32)).alias("tail_crc32"),
        F.octet_length("media").cast("bigint").alias("media_bytes"),
        F.sha2("media", 256).alias("media_sha256"),
        "feature",
    )
