"""Lossless WebP: decoder and encoder in numpy, and media columns made with them.

Decoding: prefix codes, back-references and the colour cache give coded pixels;
predictor, cross-colour, green and palette transforms are then inverted, in the
reverse of the order in which they were written. An image with one group of codes
and no colour cache is decoded for every bit offset at once: what the code at an
offset is, and where the next one starts, depends on the offset alone. Then only
the chain of offsets from the first one is walked. All other images take the plain
loop, which reads one pixel after the other.

Encoding covers the whole format, as a choice of transforms, cache, runs and code
groups; what a payload is stored with depends on its content (``plan_of``).

Payloads of any length: an image has at most 16384 rows, so longer ones become
several images, one behind the other; each says how long it is.
"""

from __future__ import annotations

import hashlib
import heapq
import zlib
from collections.abc import Iterable, Iterator
from functools import lru_cache

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from prefpat.llm.common import read_table

PREDICTOR, CROSS_COLOUR, SUBTRACT_GREEN, PALETTE = range(4)
#: Fixed values of the format.
MAX_SIDE = 1 << 14
SIGNATURE = 0x2F
LENGTH_CODES, DISTANCE_CODES = 24, 40
FIRST_CACHED = 256 + LENGTH_CODES
CODE_LENGTH_ORDER = (17, 18, 0, 1, 2, 3, 4, 5, 16, 6, 7, 8, 9, 10, 11, 12, 13, 14, 15)
CACHE_FACTOR = 0x1E35A7BD
OPAQUE_BLACK = 0xFF000000
MAX_CODE_LENGTH = 15
NEAR_DISTANCES = (
    (0, 1), (1, 0), (1, 1), (-1, 1), (0, 2), (2, 0), (1, 2), (-1, 2), (2, 1), (-2, 1), (2, 2), (-2, 2), (0, 3), (3, 0), (1, 3), (-1, 3), (3, 1), (-3, 1), (2, 3), (-2, 3),
    (3, 2), (-3, 2), (0, 4), (4, 0), (1, 4), (-1, 4), (4, 1), (-4, 1), (3, 3), (-3, 3), (2, 4), (-2, 4), (4, 2), (-4, 2), (0, 5), (3, 4), (-3, 4), (4, 3), (-4, 3), (5, 0),
    (1, 5), (-1, 5), (5, 1), (-5, 1), (2, 5), (-2, 5), (5, 2), (-5, 2), (4, 4), (-4, 4), (3, 5), (-3, 5), (5, 3), (-5, 3), (0, 6), (6, 0), (1, 6), (-1, 6), (6, 1), (-6, 1),
    (2, 6), (-2, 6), (6, 2), (-6, 2), (4, 5), (-4, 5), (5, 4), (-5, 4), (3, 6), (-3, 6), (6, 3), (-6, 3), (0, 7), (7, 0), (1, 7), (-1, 7), (5, 5), (-5, 5), (7, 1), (-7, 1),
    (4, 6), (-4, 6), (6, 4), (-6, 4), (2, 7), (-2, 7), (7, 2), (-7, 2), (3, 7), (-3, 7), (7, 3), (-7, 3), (5, 6), (-5, 6), (6, 5), (-6, 5), (8, 0), (4, 7), (-4, 7), (7, 4),
    (-7, 4), (8, 1), (8, 2), (6, 6), (-6, 6), (8, 3), (5, 7), (-5, 7), (7, 5), (-7, 5), (8, 4), (6, 7), (-6, 7), (7, 6), (-7, 6), (8, 5), (7, 7), (-7, 7), (8, 6), (8, 7),
)


def blocks(size: int, bits: int) -> int:
    return -(-size >> bits)


def palette_bits(colours: int) -> int:
    """Pixels share a byte if there are few colours: 2 to the power of this."""
    return 3 if colours <= 2 else 2 if colours <= 4 else 1 if colours <= 16 else 0


# --- prefix codes ---------------------------------------------------------------


class PrefixCode:
    """Canonical code by symbol lengths. A code of one symbol takes no bits."""

    def __init__(self, lengths: np.ndarray):
        used = np.flatnonzero(lengths)
        if len(used) == 0:
            used, lengths = np.array([0]), np.array([1])
        if len(used) == 1:
            self.set_single(int(used[0]))
            return
        order = used[np.argsort(lengths[used], kind="stable")]
        sizes = lengths[order].astype(np.int64)
        self.width = width = int(sizes[-1])
        spans = 1 << (width - sizes)  # share of the code space, in units of the longest code
        if int(spans.sum()) != 1 << width:
            raise ValueError("the prefix code is not complete")
        reverse = reversed_bits(width)
        self.symbols = np.repeat(order.astype(np.int32), spans).take(reverse)  # a reversal is its own inverse
        self.sizes = np.repeat(sizes.astype(np.uint8), spans).take(reverse)

    def set_single(self, symbol: int) -> None:
        self.width, self.symbols, self.sizes = 0, np.array([symbol], np.int32), np.zeros(1, np.uint8)

    @classmethod
    def single(cls, symbol: int) -> PrefixCode:
        code = cls.__new__(cls)
        code.set_single(symbol)
        return code


def code_arrays(lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Codes (first bit lowest) and sizes by symbol, for encoding."""
    codes, sizes = np.zeros(len(lengths), np.uint64), np.zeros(len(lengths), np.int64)
    used = np.flatnonzero(lengths)
    if len(used) > 1:
        order = used[np.argsort(lengths[used], kind="stable")]
        sizes[order] = own = lengths[order]
        spans = 1 << (own[-1] - own)
        codes[order] = reversed_bits(int(own[-1]))[np.cumsum(spans) - spans]
    return codes, sizes


REVERSED: dict[int, np.ndarray] = {0: np.zeros(1, np.int64)}


def reversed_bits(width: int) -> np.ndarray:
    if width not in REVERSED:
        shorter = reversed_bits(width - 1)
        REVERSED[width] = np.stack([shorter, shorter + (1 << (width - 1))], axis=1).reshape(-1)
        # number 2i + b reversed is i reversed over one bit less, with b on top
    return REVERSED[width]


REVERSED_7 = [reversed_bits(7 - less).tolist() for less in range(8)]


def code_lengths(counts: np.ndarray, longest: int = MAX_CODE_LENGTH) -> np.ndarray:
    """Huffman lengths, at most ``longest``; counts are flattened until they fit."""
    used = np.flatnonzero(counts).tolist()
    lengths = np.zeros(len(counts), np.int64)
    if len(used) <= 1:
        lengths[used or [0]] = 1
        return lengths
    weights = counts[used].tolist()
    while True:
        heap = [(w, i) for i, w in enumerate(weights)]
        heapq.heapify(heap)
        above = [0] * (2 * len(used) - 1)
        for node in range(len(used), 2 * len(used) - 1):
            (a, i), (b, j) = heapq.heappop(heap), heap[0]
            heapq.heapreplace(heap, (a + b, node))
            above[i] = above[j] = node
        depth = [0] * len(above)
        for node in range(len(above) - 2, -1, -1):
            depth[node] = depth[above[node]] + 1
        if max(depth[: len(used)]) <= longest:
            lengths[used] = depth[: len(used)]
            return lengths
        weights = [(w + 1) // 2 for w in weights]


# --- reading ----------------------------------------------------------------------


class BitReader:
    def __init__(self, data: bytes):
        self.data, self.at = data + bytes(64), 0
        self.end = 8 * len(data)

    def peek(self) -> int:
        start = self.at >> 3
        return int.from_bytes(self.data[start : start + 8], "little") >> (self.at & 7)

    def read(self, n: int) -> int:
        value = self.peek() & ((1 << n) - 1)
        self.at += n
        if self.at > self.end:
            raise ValueError("the image ends too early")
        return value

    def symbol(self, code: PrefixCode) -> int:
        if not code.width:
            return int(code.symbols[0])
        entry = self.peek() & ((1 << code.width) - 1)
        self.at += int(code.sizes[entry])
        if self.at > self.end:
            raise ValueError("the image ends too early")
        return int(code.symbols[entry])

    def amount(self, prefix: int) -> int:
        """A length or distance from its prefix and extra bits."""
        if prefix < 4:
            return prefix + 1
        extra = (prefix - 2) >> 1
        return ((2 + (prefix & 1)) << extra) + self.read(extra) + 1


def length_table(lengths: list[int]) -> tuple[list[tuple[int, int]], int]:
    """Symbol and size by the next bits, and how many bits: ``PrefixCode`` for small alphabets."""
    used = sorted((size, symbol) for symbol, size in enumerate(lengths) if size)
    if len(used) <= 1:
        return [(used[0][1] if used else 0, 0)], 0
    width, start = used[-1][0], 0
    table, reverse = [(0, 0)] * (1 << width), REVERSED_7[7 - width]
    for size, symbol in used:
        if start >= 1 << width:
            break
        table[reverse[start] :: 1 << size] = [(symbol, size)] * (1 << (width - size))
        start += 1 << (width - size)
    if start != 1 << width or used[-1][0] != width:
        raise ValueError("the prefix code is not complete")
    return table, width


def read_code(reader: BitReader, alphabet: int) -> PrefixCode:
    ahead = reader.peek()
    if ahead & 1:
        two, wide = ahead >> 1 & 1, 7 * (ahead >> 2 & 1)
        reader.read(4 + wide + 8 * two)
        symbol = ahead >> 3 & ((2 << wide) - 1)
        if not two:
            return PrefixCode.single(symbol)
        lengths = np.zeros(256, np.int64)
        lengths[[symbol, ahead >> (4 + wide) & 255]] = 1
        return PrefixCode(lengths)
    reader.read(1)
    lengths = np.zeros(alphabet, np.int64)
    of_lengths = [0] * 19
    for i in range(4 + reader.read(4)):
        of_lengths[CODE_LENGTH_ORDER[i]] = reader.read(3)
    table, width = length_table(of_lengths)
    left = 2 + reader.read(2 + 2 * reader.read(3)) if reader.read(1) else alphabet
    at, last, found = 0, 8, []
    mask, place = (1 << width) - 1, reader.at
    ahead, held, data = 0, 0, reader.data
    while at < alphabet and left > 0:
        left -= 1
        if held < 14:  # the most that a token takes
            ahead, held = int.from_bytes(data[place >> 3 : (place >> 3) + 64], "little") >> (place & 7), 512 - (place & 7)
        token, size = table[ahead & mask]
        if token < 16:
            found.append(token)
            last, at = token or last, at + 1
        else:
            value, least, more = (last, 3, 2) if token == 16 else (0, 3, 3) if token == 17 else (0, 11, 7)
            times = least + (ahead >> size & ((1 << more) - 1))
            size += more
            at += times
            if at > alphabet:
                raise ValueError("too many code lengths")
            found += [value] * times
        place, ahead, held = place + size, ahead >> size, held - size
    reader.at = place
    if place > reader.end:
        raise ValueError("the image ends too early")
    lengths[: len(found)] = found
    return PrefixCode(lengths)


def copy_distance(code: int, width: int) -> int:
    if code > len(NEAR_DISTANCES):
        return code - len(NEAR_DISTANCES)
    x, y = NEAR_DISTANCES[code - 1]
    return max(1, x + y * width)


def read_groups(reader: BitReader, width: int, height: int, main: bool) -> tuple:
    """What stands before coded pixels: groups of codes, which group a block has, and the cache."""
    cache_bits = reader.read(4) if reader.read(1) else 0
    group_bits, group_of = 0, None
    if main and reader.read(1):
        group_bits = reader.read(3) + 2
        group_of = read_pixels(reader, blocks(width, group_bits), blocks(height, group_bits), False) >> np.uint32(8) & np.uint32(0xFFFF)
    groups = []
    for _ in range(1 if group_of is None else int(group_of.max()) + 1):
        sizes = (256 + LENGTH_CODES + (1 << cache_bits if cache_bits else 0), 256, 256, 256, DISTANCE_CODES)
        groups.append([read_code(reader, n) for n in sizes])
    return groups, group_of, group_bits, cache_bits


def read_pixels(reader: BitReader, width: int, height: int, main: bool) -> np.ndarray:
    """Coded pixels (ARGB numbers) of an image or of a transform's data."""
    return pixels_after(reader, width, height, *read_groups(reader, width, height, main))


def pixels_after(reader, width, height, groups, group_of, group_bits, cache_bits) -> np.ndarray:
    if width * height <= FEW_PIXELS:
        return loop_pixels(reader, width, width * height, groups, group_of, group_bits, cache_bits)
    if group_of is None and not cache_bits:
        return fast_pixels(reader, width, width * height, groups[0])
    return plain_pixels(reader, width, width * height, groups, group_of, group_bits, cache_bits)


def plain_pixels(reader, width, total, groups, group_of, group_bits, cache_bits) -> np.ndarray:
    """Images with a cache or groups of codes; with a cache alone where a code ends
    depends on its offset as well, so only the pixels are taken one after the other."""
    if group_of is None and cache_bits:
        return fast_pixels(reader, width, total, groups[0], cache_bits)
    return loop_pixels(reader, width, total, groups, group_of, group_bits, cache_bits)


def loop_pixels(reader, width, total, groups, group_of, group_bits, cache_bits) -> np.ndarray:
    out, cache, shift = [0] * total, [0] * (1 << cache_bits), 32 - cache_bits
    rows = None if group_of is None else group_of.reshape(-1, blocks(width, group_bits)).tolist()
    at = 0

    def put(pixel: int) -> None:
        nonlocal at
        out[at] = pixel
        at += 1
        if cache_bits:
            cache[(CACHE_FACTOR * pixel & 0xFFFFFFFF) >> shift] = pixel

    while at < total:
        group = groups[0 if rows is None else rows[at // width >> group_bits][at % width >> group_bits]]
        symbol = reader.symbol(group[0])
        if symbol < 256:
            red, blue, alpha = (reader.symbol(c) for c in group[1:4])
            put(alpha << 24 | red << 16 | symbol << 8 | blue)
        elif symbol < 256 + LENGTH_CODES:
            length = reader.amount(symbol - 256)
            distance = copy_distance(reader.amount(reader.symbol(group[4])), width)
            if distance > at or at + length > total:
                raise ValueError("a copy leaves the image")
            for _ in range(length):
                put(out[at - distance])
        else:
            put(cache[symbol - 256 - LENGTH_CODES])
    return np.array(out, dtype=np.uint32)


#: Extra bits of a length or distance prefix, and its least value.
EXTRA_BITS = np.array([0 if p < 4 else (p - 2) >> 1 for p in range(DISTANCE_CODES)], np.int64)
LEAST_VALUE = np.array([p + 1 if p < 4 else ((2 + (p & 1)) << ((p - 2) >> 1)) + 1 for p in range(DISTANCE_CODES)], np.int64)
#: Bits decoded at a time, which bounds memory; codes and extras may go on for so many more.
SPAN_BITS, REACH_BITS = 1 << 21, 128
#: Images of so few pixels (most transforms' data) are read one pixel after the other.
FEW_PIXELS = 128


def fast_pixels(reader: BitReader, width: int, total: int, group: list[PrefixCode], cache_bits: int = 0) -> np.ndarray:
    """All bit offsets at once; see the module's text."""
    out = np.empty(total, np.uint32)
    green, red, blue, alpha, far = group
    if not (green.width or red.width or blue.width or alpha.width) and green.symbols[0] < 256:
        out[:] = int(alpha.symbols[0]) << 24 | int(red.symbols[0]) << 16 | int(green.symbols[0]) << 8 | int(blue.symbols[0])
        return out
    data = np.frombuffer(reader.data, np.uint8)
    is_far = (green.symbols >= 256) & (green.symbols < FIRST_CACHED)
    has_copies, cache = bool(is_far.any()), [0] * (1 << cache_bits)
    most = max(green.width + red.width + blue.width + alpha.width, (green.width + far.width + 2 * int(EXTRA_BITS[-1])) * has_copies)
    done = 0
    while done < total:
        if reader.at >= reader.end:
            raise ValueError("the image ends too early")
        first = reader.at >> 3
        span = min(SPAN_BITS, 8 + (total - done) * most)  # what is left takes no more
        part, windows = bit_windows(data[first : first + (span + REACH_BITS) // 8 + 4])
        n = min(len(windows) - REACH_BITS, span)
        entries = (windows[:n] & np.uint16((1 << green.width) - 1)).astype(np.intp)
        ends_at = np.arange(n) + green.sizes.take(entries)
        copies = np.flatnonzero(is_far.take(entries)) if has_copies else np.zeros(0, np.int64)
        literal_at = []
        for code in (red, blue, alpha):
            literal_at.append(ends_at if code.width else None)
            if code.width:
                ends_at = ends_at + code.sizes.take(windows.take(ends_at) & np.uint16((1 << code.width) - 1))
        if cache_bits:  # a place in the cache is all there is to read
            held = np.flatnonzero(green.symbols[entries] >= FIRST_CACHED)
            ends_at[held] = held + green.sizes[entries[held]]
        lengths = distances = None
        if len(copies):
            prefix = green.symbols[entries[copies]] - 256
            place = copies + green.sizes[entries[copies]]
            lengths = LEAST_VALUE[prefix] + extra_values(part, place, EXTRA_BITS[prefix])
            place = place + EXTRA_BITS[prefix]
            entry = windows[place] & np.uint16((1 << far.width) - 1)
            prefix = far.symbols[entry]
            place = place + far.sizes[entry]
            distances = LEAST_VALUE[prefix] + extra_values(part, place, EXTRA_BITS[prefix])
            ends_at[copies] = place + EXTRA_BITS[prefix]
        # the chain, eight codes at a step
        after = np.full(n + 1, n)
        np.minimum(ends_at, n, out=after[:n])
        two = after.take(after)
        four = two.take(two)
        eight = memoryview(four.take(four))
        at, chain = reader.at & 7, []
        limit = n
        while at < limit:
            chain.append(at)
            at = eight[at]
        places = np.array(chain, np.int64)
        for further in (four, two, after):
            places = np.stack([places, further[places]], axis=1).reshape(-1)
        places = places[places < n]
        size = np.ones(len(places), np.int64)
        if len(copies):
            where = np.searchsorted(copies, places)
            where[where == len(copies)] = 0
            is_copy = copies[where] == places
            size[is_copy] = lengths[where[is_copy]]
        ends = done + np.cumsum(size)
        count = min(len(places), int(np.searchsorted(ends, total)) + 1)
        places, size, ends = places[:count], size[:count], ends[:count]
        if ends[-1] > total:
            raise ValueError("a copy leaves the image")
        values = pixels_at(windows, places, group, literal_at)
        if cache_bits:
            symbols = green.symbols[entries[places]]
            moved = {i: (int(size[i]), copy_distance(int(distances[where[i]]), width)) for i in np.flatnonzero(is_copy[:count]).tolist()} if len(copies) else {}
            with_cache(out, done, symbols, values, moved, cache, cache_bits)
        elif len(copies) and is_copy[:count].any():
            last = 0
            for i in np.flatnonzero(is_copy[:count]).tolist():
                start = int(ends[i] - size[i])
                out[start - (i - last) : start] = values[last:i]
                length, distance = int(size[i]), copy_distance(int(distances[where[i]]), width)
                if distance > start:
                    raise ValueError("a copy leaves the image")
                out[start : start + length] = np.resize(out[start - distance : start], length) if distance < length else out[start - distance : start - distance + length]
                last = i + 1
            out[int(ends[-1]) - (count - last) : int(ends[-1])] = values[last:]
        else:
            out[done : done + count] = values
        done = int(ends[-1])
        reader.at = 8 * first + int(ends_at[places[-1]])
    if reader.at > reader.end:
        raise ValueError("the image ends too early")
    return out


def bit_windows(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Three bytes at every byte, and the next sixteen bits at every bit."""
    part = data.astype(np.uint32)
    part = part[:-2] | part[1:-1] << np.uint32(8) | part[2:] << np.uint32(16)
    windows = np.empty((len(part), 8), np.uint16)
    for s in range(8):
        windows[:, s] = part >> np.uint32(s)
    return part, windows.reshape(-1)


def with_cache(out: np.ndarray, done: int, symbols: np.ndarray, values: np.ndarray, far: dict, cache: list[int], cache_bits: int) -> None:
    """Pixels of codes that may name places of the colour cache, from ``done`` on. ``far`` has
    the length and distance of every code that is a copy."""
    shift, new, start = 32 - cache_bits, [], done
    slots = ((values.astype(np.uint64) * np.uint64(CACHE_FACTOR) & np.uint64(0xFFFFFFFF)) >> np.uint64(shift)).tolist()
    for n, (symbol, pixel, slot) in enumerate(zip(symbols.tolist(), values.tolist(), slots)):
        if symbol < 256:
            cache[slot] = pixel
            new.append(pixel)
        elif symbol >= FIRST_CACHED:
            pixel = cache[symbol - FIRST_CACHED]
            cache[(CACHE_FACTOR * pixel & 0xFFFFFFFF) >> shift] = pixel
            new.append(pixel)
        else:
            length, distance = far[n]
            at = start + len(new)
            if distance > at:
                raise ValueError("a copy leaves the image")
            for i in range(at - distance, at - distance + length):
                pixel = new[i - start] if i >= start else int(out[i])
                cache[(CACHE_FACTOR * pixel & 0xFFFFFFFF) >> shift] = pixel
                new.append(pixel)
    out[start : start + len(new)] = new


def extra_values(part: np.ndarray, places: np.ndarray, bits: np.ndarray) -> np.ndarray:
    """Values of ``bits`` bits (up to 24) at bit places."""
    whole = part[places >> 3].astype(np.int64) | part[np.minimum((places >> 3) + 3, len(part) - 1)].astype(np.int64) << 24
    return whole >> (places & 7) & ((1 << bits) - 1)


def pixels_at(windows, places, group, literal_at) -> np.ndarray:
    green = group[0]
    pixels = green.symbols.astype(np.uint32)[windows[places] & np.uint16((1 << green.width) - 1)] << np.uint32(8)
    for code, before, shift in zip((group[1], group[2], group[3]), literal_at, (16, 0, 24)):
        if not code.width:
            pixels |= np.uint32(int(code.symbols[0]) << shift)
        else:
            entry = windows[before[places]] & np.uint16((1 << code.width) - 1)
            pixels |= code.symbols[entry].astype(np.uint32) << np.uint32(shift)
    return pixels


# --- transforms -------------------------------------------------------------------


def planes(pixels: np.ndarray) -> np.ndarray:
    """ARGB numbers to a last axis of alpha, red, green, blue."""
    return np.stack([pixels >> np.uint32(s) & np.uint32(255) for s in (24, 16, 8, 0)], axis=-1).astype(np.int32)


def joined(channels: np.ndarray) -> np.ndarray:
    c = (channels & 255).astype(np.uint32)
    return c[..., 0] << np.uint32(24) | c[..., 1] << np.uint32(16) | c[..., 2] << np.uint32(8) | c[..., 3]


def predicted(mode: int, left, top, top_right, top_left):
    """What a mode predicts from the neighbours' channels (arrays or rows of them)."""
    half = lambda a, b: (a + b) >> 1
    if mode == 0 or mode > 13:
        return np.broadcast_to(np.array([255, 0, 0, 0], np.int32), np.shape(left))
    if mode <= 4:
        return (left, top, top_right, top_left)[mode - 1]
    if mode == 5:
        return half(half(left, top_right), top)
    if mode <= 9:
        return half(*((left, top_left), (left, top), (top_left, top), (top, top_right))[mode - 6])
    if mode == 10:
        return half(half(left, top_left), half(top, top_right))
    if mode == 11:
        to_left, to_top = np.abs(top - top_left).sum(-1, keepdims=True), np.abs(left - top_left).sum(-1, keepdims=True)
        return np.where(to_left < to_top, left, top)
    if mode == 12:
        return np.clip(left + top - top_left, 0, 255)
    mean = half(left, top)
    change = mean - top_left
    return np.clip(mean + (np.abs(change) >> 1) * np.sign(change), 0, 255)


def mean_of(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Halved sums of all four channels of ARGB numbers at once."""
    return (a & b) + (((a ^ b) & np.uint32(0xFEFEFEFE)) >> np.uint32(1))


def predicted_numbers(mode: int, left, top, top_right, top_left) -> np.ndarray | None:
    """What modes without a comparison or a clip predict, as ARGB numbers."""
    if mode == 0 or mode > 13:
        return np.full_like(left, OPAQUE_BLACK)
    if mode <= 4:
        return (left, top, top_right, top_left)[mode - 1]
    if mode == 5:
        return mean_of(mean_of(left, top_right), top)
    if mode <= 9:
        return mean_of(*((left, top_left), (left, top), (top_left, top), (top, top_right))[mode - 6])
    return mean_of(mean_of(left, top_left), mean_of(top, top_right)) if mode == 10 else None


def undo_predictor(pixels: np.ndarray, bits: int, modes: np.ndarray) -> np.ndarray:
    """Channels are bytes, whose sums wrap by themselves."""
    height, width = pixels.shape
    rest = np.ascontiguousarray(pixels, "<u4").view(np.uint8).reshape(height, width, 4)
    out, above = np.empty((height, width), "<u4"), np.zeros(width + 1, "<u4")
    channels = out.view(np.uint8).reshape(height, width, 4)
    np.cumsum(rest[0], axis=0, dtype=np.uint8, out=channels[0])
    channels[0, :, 3] += np.uint8(255)
    rows = modes.tolist()
    for y in range(1, height):
        above[:width] = out[y - 1]
        channels[y, 0] = rest[y, 0] + channels[y - 1, 0]
        above[width] = out[y, 0]
        x = 1
        while x < width:
            end = min(width, ((x >> bits) + 1) << bits)
            mode = rows[y >> bits][x >> bits]
            if mode == 1:
                np.cumsum(rest[y, x:end], axis=0, dtype=np.uint8, out=channels[y, x:end])
                channels[y, x:end] += channels[y, x - 1]
            elif mode in (0, 2, 3, 4, 8, 9) or mode > 13:  # nothing from the row itself
                guess = predicted_numbers(mode, above[x:end], above[x:end], above[x + 1 : end + 1], above[x - 1 : end - 1])
                np.add(rest[y, x:end], np.ascontiguousarray(guess).view(np.uint8).reshape(-1, 4), out=channels[y, x:end])
            else:
                near = planes(above)
                left = planes(out[y, x - 1 : x])[0]
                own = planes(pixels[y, x:end])
                for i in range(x, end):
                    left = (own[i - x] + predicted(mode, left, near[i], near[i + 1], near[i - 1])) & 255
                    own[i - x] = left
                out[y, x:end] = joined(own)
            x = end
    return out


def do_predictor(pixels: np.ndarray, bits: int, modes: np.ndarray) -> np.ndarray:
    height, width = pixels.shape
    padded = np.concatenate([np.zeros(width + 1, "<u4"), pixels.reshape(-1)])
    at = lambda d: padded[width + 1 - d : len(padded) - d].reshape(height, width)
    left, top, right, corner = near = at(1), at(width), at(width - 1), at(width + 1)
    guess = np.zeros((height, width), "<u4")
    for j, column in enumerate(modes.T.tolist()):
        for i, mode in enumerate(column):
            own = slice(i << bits, (i + 1) << bits), slice(j << bits, (j + 1) << bits)
            block = predicted_numbers(mode, *(n[own] for n in near))
            guess[own] = joined(predicted(mode, *(planes(n[own]) for n in near))) if block is None else block
    guess[0, 1:], guess[1:, 0], guess[0, 0] = left[0, 1:], top[1:, 0], OPAQUE_BLACK
    return (np.ascontiguousarray(pixels, "<u4").view(np.uint8) - guess.view(np.uint8)).view("<u4")


def cross_colour(pixels: np.ndarray, bits: int, elements: np.ndarray, sign: int) -> np.ndarray:
    """Adds (sign 1, undoing) or takes away (-1) what green and red say about red and blue."""
    height, width = pixels.shape
    signed = lambda x, shift: (x >> np.uint32(shift)).astype(np.uint8).view(np.int8).astype(np.int16)
    spread = lambda e: np.repeat(np.repeat(e, 1 << bits, 0), 1 << bits, 1)[:height, :width] if e.size > 1 else e
    red_by_green, blue_by_green, blue_by_red = (spread(signed(elements, s)) for s in (0, 8, 16))
    green, red = signed(pixels, 8), signed(pixels, 16)
    new_red = (red + sign * (red_by_green * green >> 5)).astype(np.int8)
    true_red = new_red if sign > 0 else red
    blue = signed(pixels, 0) + sign * ((blue_by_green * green >> 5) + (blue_by_red * true_red.astype(np.int16) >> 5))
    return pixels & np.uint32(0xFF00FF00) | new_red.view(np.uint8).astype(np.uint32) << np.uint32(16) | blue.astype(np.uint8)


def shift_green(pixels: np.ndarray, sign: int) -> np.ndarray:
    both = np.uint32(0x00FF00FF)
    green = (pixels >> np.uint32(8) & np.uint32(255)) * np.uint32(0x10001)
    moved = (pixels & both) + green if sign > 0 else (pixels & both | np.uint32(0x01000100)) - green
    return pixels & ~both | moved & both


def undo_palette(pixels: np.ndarray, width: int, palette: np.ndarray) -> np.ndarray:
    bits = palette_bits(len(palette))
    index = pixels >> np.uint32(8) & np.uint32(255)
    if bits:
        each = 8 >> bits
        index = np.stack([index >> np.uint32(each * i) & np.uint32((1 << each) - 1) for i in range(1 << bits)], axis=-1).reshape(len(pixels), -1)[:, :width]
    full = np.zeros(256, np.uint32)
    full[: len(palette)] = palette
    return full[index]


def read_header(data: bytes) -> tuple:
    """Reader at the coded pixels of the first image, their shape, the transforms to undo, and the image's bytes."""
    if data[:4] != b"RIFF" or data[8:16] != b"WEBPVP8L":
        raise ValueError("not a lossless image of this kind")
    whole, size = int.from_bytes(data[4:8], "little") + 8, int.from_bytes(data[16:20], "little")
    if len(data) < whole or whole < 20 + size:
        raise ValueError("the image ends too early")
    reader = BitReader(data[20 : 20 + size])
    if reader.read(8) != SIGNATURE:
        raise ValueError("no signature")
    width, height, _, version = reader.read(14) + 1, reader.read(14) + 1, reader.read(1), reader.read(3)
    if version:
        raise ValueError("unknown version")
    undo, coded_width = [], width
    while reader.read(1):
        kind = reader.read(2)
        if kind in (PREDICTOR, CROSS_COLOUR):
            bits = reader.read(3) + 2
            shape = blocks(height, bits), blocks(coded_width, bits)
            undo.append((kind, bits, read_pixels(reader, shape[1], shape[0], False).reshape(shape)))
        elif kind == PALETTE:
            count = reader.read(8) + 1
            colours = joined(np.cumsum(planes(read_pixels(reader, count, 1, False)), axis=0))
            undo.append((kind, coded_width, colours))
            coded_width = blocks(coded_width, palette_bits(count))
        else:
            undo.append((kind,))
    return reader, coded_width, height, undo, whole


def undone(pixels: np.ndarray, undo: list[tuple]) -> np.ndarray:
    for kind, *more in reversed(undo):
        if kind == PREDICTOR:
            pixels = undo_predictor(pixels, more[0], (more[1] >> np.uint32(8) & np.uint32(255)).astype(int))
        elif kind == CROSS_COLOUR:
            pixels = cross_colour(pixels, *more, 1)
        elif kind == PALETTE:
            pixels = undo_palette(pixels, *more)
        else:
            pixels = shift_green(pixels, 1)
    return pixels


def decode_image(data: bytes) -> tuple[np.ndarray, int]:
    """Pixels (height x width ARGB numbers) of the first image, and its bytes."""
    reader, width, height, undo, whole = read_header(data)
    return undone(read_pixels(reader, width, height, True).reshape(height, width), undo), whole


# --- writing -----------------------------------------------------------------------


class BitWriter:
    """Arrays of (values, sizes) in order, joined at the end."""

    def __init__(self):
        self.values, self.sizes = [], []
        self.loose: list[tuple[int, int]] = []

    def write(self, value: int, size: int) -> None:
        self.loose.append((value, size))

    def write_all(self, values: np.ndarray, sizes: np.ndarray) -> None:
        self.flush()
        self.values.append(values)
        self.sizes.append(sizes)

    def flush(self) -> None:
        if self.loose:
            values, sizes = zip(*self.loose)
            self.values.append(np.array(values, np.uint64))
            self.sizes.append(np.array(sizes, np.int64))
            self.loose = []

    def to_bytes(self) -> bytes:
        self.flush()
        values, sizes = np.concatenate(self.values), np.concatenate(self.sizes)
        ends = np.cumsum(sizes)
        return packed(values, sizes, ends - sizes)[: -(-int(ends[-1]) // 8)]


def packed(values: np.ndarray, sizes: np.ndarray, starts: np.ndarray) -> bytes:
    """Values of some bits each, put at rising bit places."""
    keep = np.flatnonzero(sizes)
    values, starts = values[keep], starts[keep]
    word = starts >> 5
    shifted = values << (starts & 31).astype(np.uint64)
    first = np.flatnonzero(np.r_[True, word[1:] != word[:-1]])
    out = np.zeros(int(word[-1]) + 2, np.uint64)
    out[word[first]] |= np.bitwise_or.reduceat(shifted & np.uint64(0xFFFFFFFF), first)
    out[word[first] + 1] |= np.bitwise_or.reduceat(shifted >> np.uint64(32), first)
    return out.astype("<u4").tobytes()


def write_code(writer: BitWriter, lengths: np.ndarray) -> None:
    used = np.flatnonzero(lengths).tolist()
    if len(used) <= 2 and all(u < 256 for u in used):
        write_simple_code(writer, used)
        return
    tokens: list[tuple[int, int, int]] = []  # symbol, extra value, extra bits
    first = np.flatnonzero(np.r_[True, lengths[1:] != lengths[:-1]])
    for value, times in zip(lengths[first].tolist(), np.diff(np.r_[first, len(lengths)]).tolist()):
        if value:
            tokens.append((value, 0, 0))
            times -= 1
        while times >= 3:
            most, symbol, bits = (6, 16, 2) if value else (138, 18, 7) if times > 10 else (10, 17, 3)
            now = min(times, most)
            tokens.append((symbol, now - (11 if symbol == 18 else 3), bits))
            times -= now
        tokens += [(value, 0, 0)] * times
    counts = np.bincount([t[0] for t in tokens], minlength=19)
    sizes = code_lengths(counts, 7)
    codes, of = (x.tolist() for x in code_arrays(sizes))
    count = max(4, 1 + max(i for i, s in enumerate(CODE_LENGTH_ORDER) if sizes[s]))
    writer.write(0, 1)
    writer.write(count - 4, 4)
    for s in CODE_LENGTH_ORDER[:count]:
        writer.write(int(sizes[s]), 3)
    writer.write(0, 1)  # the whole alphabet follows
    for symbol, value, bits in tokens:
        writer.write(codes[symbol] | value << of[symbol], of[symbol] + bits)


def write_simple_code(writer: BitWriter, symbols: list[int]) -> None:
    """A code of one or two symbols below 256."""
    writer.write(1, 1)
    writer.write(len(symbols) - 1, 1)
    writer.write(1, 1)
    for symbol in symbols:
        writer.write(symbol, 8)


def prefix_of(values: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Prefix, extra value and extra bits of lengths or distances."""
    prefix = np.searchsorted(LEAST_VALUE, values, side="right") - 1
    return prefix, values - LEAST_VALUE[prefix], EXTRA_BITS[prefix]


def long_runs(pixels: np.ndarray, begins: np.ndarray | int = 0, least: int = 4, most: int = 4096) -> tuple[np.ndarray, np.ndarray]:
    """Starts and lengths of copies from one pixel before, none over the begin of an image."""
    new = np.empty(len(pixels), bool)
    np.not_equal(pixels[1:], pixels[:-1], out=new[1:])
    new[begins] = True
    first = np.flatnonzero(new)
    sizes = np.diff(np.r_[first, len(pixels)]) - 1
    first, sizes = first[sizes >= least] + 1, sizes[sizes >= least]
    parts = -(-sizes // most)
    owner = np.repeat(np.arange(len(sizes)), parts)
    at = np.arange(len(owner)) - np.repeat(np.cumsum(parts) - parts, parts)
    return first[owner] + at * most, np.minimum(sizes[owner] - at * most, most)


def write_pixels(writer: BitWriter, pixels: np.ndarray, main: bool, runs: bool = False, cache_bits: int = 0, group_bits: int = 0) -> None:
    """Entropy-coded pixels. ``group_bits`` gives blocks with codes of their own, by turns two."""
    height, width = pixels.shape
    flat = pixels.reshape(-1)
    starts, sizes = long_runs(flat) if runs else (np.zeros(0, np.int64), np.zeros(0, np.int64))
    is_token = np.ones(len(flat), bool)
    if len(starts):
        depth = np.zeros(len(flat) + 1, np.int64)
        depth[starts] += 1
        depth[starts + sizes] -= 1
        is_token = np.cumsum(depth[:-1]) == 0
        is_token[starts] = True
    places = np.flatnonzero(is_token)
    copy = np.zeros(len(places), bool)
    copy[np.searchsorted(places, starts)] = True
    own = flat[places]
    green = (own >> np.uint32(8) & np.uint32(255)).astype(np.int64)
    cached = np.zeros(len(places), bool)
    if cache_bits:
        slots = ((flat.astype(np.uint64) * np.uint64(CACHE_FACTOR) & np.uint64(0xFFFFFFFF)) >> np.uint64(32 - cache_bits)).tolist()
        cache, hits = [0] * (1 << cache_bits), []
        for slot, pixel in zip(slots, flat.tolist()):
            hits.append(cache[slot] == pixel)
            cache[slot] = pixel
        cached = np.array(hits)[places] & ~copy
        green[cached] = 256 + LENGTH_CODES + np.array(slots)[places][cached]
    extra, extra_bits = np.zeros(len(places), np.int64), np.zeros(len(places), np.int64)
    prefix, extra[copy], extra_bits[copy] = prefix_of(sizes)
    green[copy] = 256 + prefix
    literal = ~(copy | cached)
    far_prefix = int(prefix_of(np.array([1 + NEAR_DISTANCES.index((1, 0))]))[0][0])
    writer.write(int(cache_bits > 0), 1)
    if cache_bits:
        writer.write(cache_bits, 4)
    group, groups = np.zeros(len(places), np.int64), 1
    if main:
        writer.write(int(group_bits > 0), 1)
        if group_bits:
            shape = blocks(height, group_bits), blocks(width, group_bits)
            turns = np.add.outer(np.arange(shape[0]), np.arange(shape[1])) % 2
            writer.write(group_bits - 2, 3)
            write_pixels(writer, (turns.astype(np.uint32) << np.uint32(8)) | np.uint32(OPAQUE_BLACK), False)
            group, groups = turns[places // width >> group_bits, places % width >> group_bits], int(turns.max()) + 1
    alphabet = 256 + LENGTH_CODES + (1 << cache_bits if cache_bits else 0)
    same, any_ = int(np.bitwise_and.reduce(own)), int(np.bitwise_or.reduce(own))
    plain = [s for s in (16, 0, 24) if (same ^ any_) >> s & 255 == 0]  # channels of one value
    coded = [s for s in (16, 0, 24) if s not in plain]
    values, bits = np.empty((len(places), 1 + len(coded)), np.uint64), np.zeros((len(places), 1 + len(coded)), np.int64)
    for g in range(groups):
        mine = group == g if group_bits else slice(None)
        symbols = green[mine]
        lengths = code_lengths(np.bincount(symbols, minlength=alphabet))
        write_code(writer, lengths)
        code, size = code_arrays(lengths)
        # a copy's extra bits follow its code; its distance is always one pixel, which takes none
        values[mine, 0] = code[symbols] | extra[mine].astype(np.uint64) << size[symbols].astype(np.uint64)
        bits[mine, 0] = size[symbols] + extra_bits[mine]
        for shift in (16, 0, 24):
            if shift in plain:
                write_simple_code(writer, [same >> shift & 255])
                continue
            c = 1 + coded.index(shift)
            apart = literal & (group == g)
            symbols = (own[apart] >> np.uint32(shift) & np.uint32(255)).astype(np.int64)
            lengths = code_lengths(np.bincount(symbols, minlength=256))
            write_code(writer, lengths)
            code, size = code_arrays(lengths)
            values[apart, c], bits[apart, c] = code[symbols], size[symbols]
        write_simple_code(writer, [far_prefix])
    writer.write_all(values.reshape(-1), bits.reshape(-1))


def write_shape(writer: BitWriter, height: int, width: int) -> None:
    for value, size in ((SIGNATURE, 8), (width - 1, 14), (height - 1, 14), (1, 1), (0, 3)):
        writer.write(value, size)


def encode_image(pixels: np.ndarray, transforms: tuple = (), runs: bool = True, cache_bits: int = 0, group_bits: int = 0) -> bytes:
    """One image. Transforms, in order: ``(PREDICTOR, bits, modes)``, ``(CROSS_COLOUR,
    bits, elements)``, ``(SUBTRACT_GREEN,)``, ``(PALETTE,)``."""
    height, width = pixels.shape
    writer = BitWriter()
    write_shape(writer, height, width)
    for kind, *more in transforms:
        writer.write(1, 1)
        writer.write(kind, 2)
        if kind in (PREDICTOR, CROSS_COLOUR):
            bits, data = more
            writer.write(bits - 2, 3)
            if kind == PREDICTOR:
                write_pixels(writer, (data.astype(np.uint32) << np.uint32(8)) | np.uint32(OPAQUE_BLACK), False)
                pixels = do_predictor(pixels, bits, data)
            else:
                write_pixels(writer, data, False)
                pixels = cross_colour(pixels, bits, data, -1)
        elif kind == PALETTE:
            colours, pixels = indexed(pixels)
            writer.write(len(colours) - 1, 8)
            steps = planes(colours)
            steps[1:] -= steps[:-1].copy()
            write_pixels(writer, joined(steps).reshape(1, -1), False)
        else:
            pixels = shift_green(pixels, -1)
    writer.write(0, 1)
    write_pixels(writer, pixels, True, runs, cache_bits, group_bits)
    return contained(writer.to_bytes())


def contained(data: bytes) -> bytes:
    padded = data + bytes(len(data) % 2)
    return b"RIFF" + (12 + len(padded)).to_bytes(4, "little") + b"WEBPVP8L" + len(data).to_bytes(4, "little") + padded


def indexed(pixels: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Colours, and the coded pixels that name them."""
    colours, index = np.unique(pixels, return_inverse=True)
    if len(colours) > 256:
        raise ValueError("too many colours for a palette")
    return colours, bundled(index.reshape(pixels.shape).astype(np.uint32), palette_bits(len(colours)))


def bundled(index: np.ndarray, bits: int) -> np.ndarray:
    if bits:
        height, width = index.shape
        each, count = 8 >> bits, blocks(width, bits)
        index = np.pad(index, ((0, 0), (0, (count << bits) - width))).reshape(height, count, 1 << bits)
        index = (index << (np.arange(1 << bits, dtype=np.uint32) * np.uint32(each))).sum(axis=-1, dtype=np.uint32)
    return index << np.uint32(8) | np.uint32(OPAQUE_BLACK)


# --- many images at once -------------------------------------------------------------
# The same coding as above, byte for byte, for the small images of which a table of texts
# is full: arrays go over all images, or a step is made for all of them at a time.

#: Texts stored and read back together: this many bytes; a longer one by itself, in the plain form.
TOGETHER = 1 << 20


def code_lengths_many(counts: np.ndarray, longest: int = MAX_CODE_LENGTH) -> np.ndarray:
    """``code_lengths`` of every row. Nodes come with rising weight, so the least two are the
    first of the sorted leaves or of the nodes not yet joined; one joining of all rows a step."""
    lengths, used = np.zeros(counts.shape, np.int64), np.count_nonzero(counts, axis=1)
    few = np.flatnonzero(used <= 1)
    lengths[few, np.argmax(counts[few] > 0, axis=1)] = 1
    rows = np.flatnonzero(used > 1)
    if not len(rows):
        return lengths
    rows = rows[np.argsort(-used[rows], kind="stable")]
    used = used[rows]
    most, many, every = int(used[0]), len(rows), np.arange(len(rows))
    weights = np.where(counts[rows] > 0, counts[rows], 1 << 60)
    order = np.argsort(weights, axis=1, kind="stable")[:, :most]
    nodes = (most + 1) * many  # leaves stand before nodes, a row of the table for each place
    weight, above = np.full(2 * nodes, 1 << 60), np.zeros(2 * nodes, np.int64)
    weight[: most * many] = np.take_along_axis(weights, order, 1).T.reshape(-1)
    leaf, node = every.copy(), every + nodes
    active = np.searchsorted(-used, -np.arange(1, most)).tolist()  # rows with a joining left
    for step, m in enumerate(active):
        total = np.zeros(m, np.int64)
        for _ in range(2):
            a, b = weight[leaf[:m]], weight[node[:m]]
            is_leaf = a <= b
            above[np.where(is_leaf, leaf[:m], node[:m])] = step
            total += np.minimum(a, b)
            leaf[:m] += is_leaf * many
            node[:m] += ~is_leaf * many
        weight[nodes + step * many : nodes + step * many + m] = total
    depth, above = np.zeros(nodes, np.int64), above.reshape(2, most + 1, many)
    for step in range(most - 3, -1, -1):
        m = active[step + 1]
        depth[step * many : step * many + m] = depth[above[1, step, :m] * many + every[:m]] + 1
    found = (depth[above[0, :most] * many + every] + 1).T * (np.arange(most) < used[:, None])
    lengths[rows[:, None], order] = found
    deep = rows[found.max(axis=1) > longest]
    if len(deep):
        lengths[deep] = code_lengths_many((counts[deep] + 1) // 2, longest)
    return lengths


def code_arrays_many(lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """``code_arrays`` of every row."""
    order = np.argsort(np.where(lengths > 0, lengths, 99), axis=1, kind="stable")
    own = np.take_along_axis(lengths, order, 1)
    spans = np.where(own > 0, 1 << (MAX_CODE_LENGTH - own), 0)
    codes, sizes = np.zeros(lengths.shape, np.uint64), np.where((own > 0).sum(axis=1, keepdims=True) > 1, lengths, 0)
    starts = reversed_bits(MAX_CODE_LENGTH)[(np.cumsum(spans, axis=1) - spans) & ((1 << MAX_CODE_LENGTH) - 1)]
    np.put_along_axis(codes, order, starts.astype(np.uint64), 1)
    return np.where(sizes > 0, codes, np.uint64(0)), sizes


Bits = tuple[np.ndarray, np.ndarray]


def written_codes(lengths: np.ndarray) -> list[Bits]:
    """What ``write_code`` writes for every row."""
    many, alphabet = lengths.shape
    used = np.count_nonzero(lengths, axis=1)
    simple = (used <= 2) & ~lengths[:, 256:].any(axis=1)
    values, sizes = np.zeros((many, 21), np.uint64), np.zeros((many, 21), np.uint8)
    lowest, highest = np.argmax(lengths > 0, axis=1), alphabet - 1 - np.argmax(lengths[:, ::-1] > 0, axis=1)
    values[simple, 0], sizes[simple, 0] = (5 + 2 * (used - 1) + (lowest << 3))[simple], 11
    values[simple, 1], sizes[simple, 1] = highest[simple], 8 * (used[simple] - 1)
    rows = np.flatnonzero(~simple)
    if not len(rows):
        return list(zip(values, sizes))
    flat = lengths[rows].reshape(-1)
    new = np.empty(len(flat), bool)
    np.not_equal(flat[1:], flat[:-1], out=new[1:])
    new[::alphabet] = True
    first = np.flatnonzero(new)
    times, value = np.diff(np.r_[first, len(flat)]), flat[first]
    once = (value > 0).astype(np.int64)
    most, times = np.where(value > 0, 6, 138), times - once
    whole, rest = times // most, times % most
    each = once + whole + np.where(rest >= 3, 1, rest)
    run = np.repeat(np.arange(len(first)), each)
    place = np.arange(len(run)) - np.repeat(np.cumsum(each) - each, each) - once[run]  # -1: the length itself
    value, most = value[run], most[run]
    now = np.where(place < 0, 0, np.where(place < whole[run], most, np.where(rest[run] >= 3, rest[run], 0)))
    symbol = np.where(now == 0, value, np.where(value > 0, 16, np.where(now > 10, 18, 17)))
    owner = first[run] // alphabet
    of_sizes = code_lengths_many(np.bincount(owner * 19 + symbol, minlength=19 * len(rows)).reshape(-1, 19), 7)
    codes, bits = code_arrays_many(of_sizes)
    in_order = of_sizes[:, CODE_LENGTH_ORDER]
    count = np.maximum(4, 19 - np.argmax(in_order[:, ::-1] > 0, axis=1))
    values[rows, 0], sizes[rows, 0] = (count - 4) << 1, 5
    values[rows, 1:20], sizes[rows, 1:20] = in_order, 3 * (np.arange(19) < count[:, None])
    sizes[rows, 20] = 1  # the whole alphabet follows
    size, more = bits[owner, symbol].astype(np.uint8), np.array([0] * 16 + [2, 3, 7], np.uint8)[symbol]
    tokens = codes[owner, symbol] | (now - np.where(symbol == 18, 11, 3) * (now > 0)).astype(np.uint64) << size.astype(np.uint64), size + more
    ends = np.cumsum(np.bincount(owner, minlength=len(rows))).tolist()
    out, start = list(zip(values, sizes)), 0
    for row, end in zip(rows.tolist(), ends):
        out[row] = np.concatenate([values[row], tokens[0][start:end]]), np.concatenate([sizes[row], tokens[1][start:end]])
        start = end
    return out


def slots_of(pixels: np.ndarray, cache_bits: int) -> np.ndarray:
    return ((pixels.astype(np.uint64) * np.uint64(CACHE_FACTOR) & np.uint64(0xFFFFFFFF)) >> np.uint64(32 - cache_bits)).astype(np.int64)


def written_pixels(images: list[np.ndarray], main: bool, runs: bool, cache_bits: int) -> list[list[Bits]]:
    """What ``write_pixels`` writes for every image, without groups of codes."""
    flat, many = np.concatenate([i.reshape(-1) for i in images]), len(images)
    each = np.array([i.size for i in images])
    begins = np.cumsum(each) - each
    owner = np.repeat(np.arange(many), each)
    starts, sizes = long_runs(flat, begins) if runs else (np.zeros(0, np.int64), np.zeros(0, np.int64))
    depth = np.zeros(len(flat) + 1, np.int8)
    depth[starts] += 1
    depth[starts + sizes] -= 1
    is_token = np.cumsum(depth[:-1], dtype=np.int8) == 0
    is_token[starts] = True
    places = np.flatnonzero(is_token)
    copies = np.searchsorted(places, starts)
    own, owner_of = flat[places], owner[places]
    green = (own >> np.uint32(8) & np.uint32(255)).astype(np.int64)
    literal = np.ones(len(places), bool)
    if cache_bits:
        slots = slots_of(flat, cache_bits)
        key = owner << cache_bits | slots
        order = np.argsort(key, kind="stable")
        sorted_key, held = key[order], flat[order]
        before = np.r_[np.uint32(0), held[:-1]]
        before[np.r_[True, sorted_key[1:] != sorted_key[:-1]]] = 0
        hits = np.empty(len(flat), bool)
        hits[order] = before == held
        literal = ~hits[places]
        green[~literal] = FIRST_CACHED + slots[places][~literal]
    prefix, extra, extra_bits = prefix_of(sizes)
    green[copies], literal[copies] = 256 + prefix, False
    alphabet = FIRST_CACHED + (1 << cache_bits if cache_bits else 0)
    at = np.searchsorted(places, begins)
    same, any_ = np.bitwise_and.reduceat(own, at), np.bitwise_or.reduceat(own, at)
    columns, parts = [], []
    for shift in (8, 16, 0, 24):
        if shift == 8:
            keys = owner_of * alphabet + green
            counts = np.bincount(keys, minlength=many * alphabet).reshape(many, alphabet)
        else:
            varies = ((same ^ any_) >> np.uint32(shift) & np.uint32(255)) > 0
            counts = np.zeros((many, 256), np.int64)
            counts[np.arange(many), same >> np.uint32(shift) & np.uint32(255)] = ~varies
            if varies.any():
                mine = np.flatnonzero(literal & varies[owner_of])
                keys = owner_of[mine] * 256 + (own[mine] >> np.uint32(shift) & np.uint32(255))
                counts += np.bincount(keys, minlength=many * 256).reshape(many, 256)
        lengths = code_lengths_many(counts)
        parts.append(written_codes(lengths))
        if shift == 8:
            codes, bits = code_arrays_many(lengths)
            values, size = codes.take(keys), bits.astype(np.uint8).take(keys)
            values[copies] |= extra.astype(np.uint64) << size[copies].astype(np.uint64)
            size[copies] += extra_bits.astype(np.uint8)
            columns.append((values, size))
        elif varies.any():
            codes, bits = code_arrays_many(lengths)
            values, size = np.zeros(len(places), np.uint64), np.zeros(len(places), np.uint8)
            values[mine], size[mine] = codes.take(keys), bits.astype(np.uint8).take(keys)
            columns.append((values, size))
    values, bits = columns[0] if len(columns) == 1 else (np.stack(c, axis=1).reshape(-1) for c in zip(*columns))
    writer = BitWriter()
    writer.write(int(cache_bits > 0) | cache_bits << 1, 5 if cache_bits else 1)
    if main:
        writer.write(0, 1)
    writer.flush()
    head = writer.values[0], writer.sizes[0]
    write_simple_code(writer, [int(prefix_of(np.array([1 + NEAR_DISTANCES.index((1, 0))]))[0][0])])
    writer.flush()
    far = writer.values[1], writer.sizes[1]
    at, width = np.r_[at, len(places)].tolist(), len(columns)
    return [[head, *codes, far, (values[width * a : width * b], bits[width * a : width * b])] for a, b, *codes in zip(at, at[1:], *parts)]


@lru_cache(maxsize=256)
def written_data(kind: int, bits: int, shape: tuple[int, int], data: bytes) -> Bits:
    """A transform with its data; few are different."""
    writer = BitWriter()
    for value, size in ((1, 1), (kind, 2), (bits - 2, 3)):
        writer.write(value, size)
    write_pixels(writer, np.frombuffer(data, np.uint32).reshape(shape), False)
    writer.flush()
    return np.concatenate(writer.values), np.concatenate(writer.sizes)


def encode_images(images: list[tuple[np.ndarray, dict]]) -> list[bytes]:
    """``encode_image`` of pixels and the options that ``plan_of`` gives, for all of them."""
    pieces: list[list[Bits]] = []
    palettes, mains = [], {}
    for n, (pixels, plan) in enumerate(images):
        writer, kind = BitWriter(), None
        write_shape(writer, *pixels.shape)
        writer.flush()
        mine = [(writer.values[0], writer.sizes[0])]
        for kind, *more in plan.get("transforms", ()):
            if kind in (PREDICTOR, CROSS_COLOUR):
                bits, data = more
                coded = (data.astype(np.uint32) << np.uint32(8)) | np.uint32(OPAQUE_BLACK) if kind == PREDICTOR else data
                mine.append(written_data(kind, bits, coded.shape, coded.tobytes()))
                pixels = do_predictor(pixels, bits, data) if kind == PREDICTOR else cross_colour(pixels, bits, data, -1)
            elif kind == PALETTE:
                colours, pixels = indexed(pixels)
                mine.append((np.array([1, kind, len(colours) - 1], np.uint64), np.array([1, 2, 8])))
                steps = planes(colours)
                steps[1:] -= steps[:-1].copy()
                palettes.append((n, len(mine), joined(steps)))
                mine.append(mine[0])  # its place
            else:
                mine.append((np.array([1, kind], np.uint64), np.array([1, 2])))
                pixels = shift_green(pixels, -1)
        mine.append((np.zeros(1, np.uint64), np.ones(1, np.int64)))
        pieces.append(mine)
        # like with like: the same columns of channels
        mains.setdefault((plan.get("cache_bits", 0), kind in (CROSS_COLOUR, SUBTRACT_GREEN)), []).append((n, pixels))
    if palettes:
        for (n, place, _), written in zip(palettes, written_pixels([p for *_, p in palettes], False, False, 0)):
            pieces[n][place : place + 1] = written
    for (cache_bits, _), own in mains.items():
        for (n, _), written in zip(own, written_pixels([p for _, p in own], True, True, cache_bits)):
            pieces[n] += written
    values, sizes = zip(*(bits for mine in pieces for bits in mine))
    values, sizes = np.concatenate(values), np.concatenate(sizes, dtype=np.uint8, casting="unsafe")  # 30 bits at most
    ends = np.cumsum(sizes, dtype=np.int64)
    last = np.cumsum([sum(len(v) for v, _ in mine) for mine in pieces])
    filled = ends[last - 1]
    bits = np.diff(np.r_[0, filled])
    wide = -(-bits >> 6) << 6  # every image from a whole word on
    begin = np.cumsum(wide) - wide
    ends += np.repeat(begin - (filled - bits), np.diff(np.r_[0, last]))
    ends -= sizes
    data = packed(values, sizes, ends)
    return [contained(data[b >> 3 : (b >> 3) + -(-n // 8)]) for b, n in zip(begin.tolist(), bits.tolist())]


#: Bits of coded pixels that are read from a guessed place on, side by side with all others;
#: and how far the reading before goes on until it meets one of its codes.
PIECE_BITS, MEET_BITS = 4096, 1024
#: Codes read between looks at which pieces are at their end.
STEPS = 64


def decode_images(data: list[bytes]) -> list[tuple[np.ndarray, int]]:
    """``decode_image`` of everything. Images of which only green is coded are read side by side;
    others, where pieces seldom meet, and those that ``side_by_side`` leaves, by themselves."""
    out: list = []
    alike: list[int] = []
    pixels: dict[int, np.ndarray] = {}
    for n, one in enumerate(data):
        reader, width, height, undo, whole = read_header(one)
        coded = read_groups(reader, width, height, True)
        out.append((reader, width, height, coded, undo, whole))
        green, *colours, far = coded[0][0]
        near = not far.width and far.symbols[0] < 4 and copy_distance(int(far.symbols[0]) + 1, width) == 1
        if coded[1] is None and near and green.width and not any(c.width for c in colours) and reader.at < reader.end:
            alike.append(n)
    if alike:
        readers, totals, coded = [out[n][0] for n in alike], [out[n][1] * out[n][2] for n in alike], [out[n][3] for n in alike]
        found = side_by_side(readers, np.array(totals), [c[0][0] for c in coded], np.array([c[3] for c in coded]))
        pixels |= {n: p for n, p in zip(alike, found) if p is not None}
    for n, (reader, width, height, coded, undo, whole) in enumerate(out):
        own = pixels[n] if n in pixels else pixels_after(reader, width, height, *coded)
        out[n] = undone(own.reshape(height, width), undo), whole
    return out


def side_by_side(readers: list[BitReader], totals: np.ndarray, groups: list[list[PrefixCode]], cache_bits: np.ndarray) -> list[np.ndarray | None]:
    """Pixels of images of which only green is coded and whose copies are all from one pixel
    before; none for an image that the general form has to judge: a broken one, or one whose
    pieces do not meet.

    A piece that begins at a guessed bit soon falls in with the true codes. What comes from
    there on depends on the place alone, so a piece counts from the first place that the
    piece before, itself read from a true code on, has in common with it."""
    many, sizes = len(readers), [len(r.data) for r in readers]
    offsets = 8 * (np.cumsum(sizes) - sizes)
    starts, limits = (offsets + np.array([getattr(r, end) for r in readers]) for end in ("at", "end"))
    raw = np.frombuffer(b"".join(r.data for r in readers) + bytes(2), np.uint8).astype(np.int64)
    words = raw[:-2] | raw[1:-1] << 8 | raw[2:] << 16
    span = limits - starts
    parts = np.maximum(1, span // PIECE_BITS)
    image, first_piece = np.repeat(np.arange(many), parts), np.cumsum(parts) - parts
    begin = starts[image] + (np.arange(len(image)) - first_piece[image]) * (span // parts)[image]
    final = np.r_[image[1:] != image[:-1], True]
    stop = np.where(final, limits[image], np.r_[begin[1:], 0] + MEET_BITS)
    room = np.array([len(g[0].symbols) for g in groups])
    symbols, table = np.concatenate([g[0].symbols for g in groups]), np.concatenate([g[0].sizes for g in groups]).astype(np.int32)
    copy = np.flatnonzero((symbols >= 256) & (symbols < FIRST_CACHED))
    table[copy] += EXTRA_BITS[symbols[copy] - 256].astype(np.int32)  # a copy's bits are read later
    table |= symbols << 6
    bases, masks = (np.cumsum(room) - room)[image], (room - 1)[image]
    at, piece, step, found, count = begin.copy(), np.arange(len(image)), 0, [], np.zeros(len(image), np.int64)
    while len(piece):
        read = np.empty((STEPS, len(piece)), np.int32)
        for k in range(STEPS):
            entry = table.take((words.take(at >> 3, mode="clip") >> (at & 7) & masks) + bases)
            read[k] = entry
            at += entry & 63
        inside = at - np.cumsum((read & 63)[::-1], axis=0)[::-1] < stop[piece]
        count[piece] += inside.sum(axis=0)
        found.append((step, piece, inside, read))
        step += STEPS
        keep = at < stop[piece]
        if not keep.all():
            at, piece, bases, masks = at[keep], piece[keep], bases[keep], masks[keep]
    base, codes = np.cumsum(count) - count, int(count.sum())
    read = np.empty(codes, np.int32)
    for step, piece, inside, block in found:
        read[(base[piece] + np.arange(step, step + STEPS)[:, None])[inside]] = block[inside]
    del found
    taken = np.cumsum(read & 63, dtype=np.int64)
    place = np.r_[0, taken[:-1]]
    place += np.repeat(begin - place[base], count)
    # where pieces meet; a piece's places come after those of the one before
    lift = np.arange(len(image)) * (1 << 40)
    keys = place + np.repeat(lift, count)
    inner = np.flatnonzero(~final)
    tail = np.searchsorted(keys, lift[inner] + begin[inner + 1])
    tail = ranges(tail, base[inner] + count[inner] - tail)
    wanted = keys[tail] + (1 << 40)
    same = np.minimum(np.searchsorted(keys, wanted), codes - 1)
    hit = keys[same] == wanted
    met, at_first = np.unique(wanted[hit] >> 40, return_index=True)
    since, until, whole = base.copy(), base + count, final.copy()
    since[met], until[met - 1], whole[met - 1] = same[hit][at_first], tail[hit][at_first], True
    whole = np.logical_and.reduceat(whole, first_piece)
    number = np.where(whole[image], np.maximum(0, until - since), 0)
    chosen = ranges(since, number)
    number = np.add.reduceat(number, first_piece)
    read, owner = read[chosen], np.repeat(np.arange(many), number)
    green, length = read >> 6, np.ones(len(read), np.int64)
    copies = np.flatnonzero((green >= 256) & (green < FIRST_CACHED))
    prefix = green[copies] - 256
    further = place[chosen[copies]] + (read[copies] & 63) - EXTRA_BITS[prefix]
    length[copies] = LEAST_VALUE[prefix] + (words.take(further >> 3, mode="clip") >> (further & 7) & ((1 << EXTRA_BITS[prefix]) - 1))
    ends, first = np.r_[0, np.cumsum(length)], np.cumsum(number) - number
    enough = np.searchsorted(ends, ends[first] + totals) - first  # what comes then fills the last byte
    whole &= (enough <= number) & (ends[first + np.minimum(enough, number)] - ends[first] == totals)
    length[ranges(first + np.where(whole, enough, 0), np.where(whole, number - enough, number))] = 0
    own = np.flatnonzero(whole)
    last = first[own] + enough[own] - 1
    whole[own] = (place[chosen[last]] + (read[last] & 63) <= limits[own]) & ((green[first[own]] < 256) | (green[first[own]] >= FIRST_CACHED))
    plain = np.array([int(g[1].symbols[0]) << 16 | int(g[2].symbols[0]) | int(g[3].symbols[0]) << 24 for g in groups], np.uint32)
    values = (green & 255).astype(np.uint32) << np.uint32(8) | np.repeat(plain, number)
    cached = np.flatnonzero(np.repeat(cache_bits > 0, number))
    cached = cached[(green[cached] < 256) | (green[cached] >= FIRST_CACHED)]  # copies put nothing new
    if len(cached):
        literal, whose = green[cached] < 256, owner[cached]
        hashes = values[cached].astype(np.uint64) * np.uint64(CACHE_FACTOR) & np.uint64(0xFFFFFFFF)
        slots = np.where(literal, (hashes >> (32 - cache_bits[whose]).astype(np.uint64)).astype(np.int64), green[cached] - FIRST_CACHED)
        slots += whose << 15
        order = np.argsort(slots, kind="stable")
        slots, put = slots[order], np.maximum.accumulate(np.where(literal[order], np.arange(len(order)), -1))
        whole[whose[order[(put < 0) | (slots[put] != slots)]]] = False  # never put
        values[cached[order]] = values[cached[order[put]]]
    if len(copies):  # a copy is the pixel before; another copy may be before it
        is_copy = np.zeros(len(green), bool)
        is_copy[copies] = True
        values[copies] = values[np.maximum.accumulate(np.where(is_copy, 0, np.arange(len(green))))[copies]]
    pixels = np.repeat(values, length)
    ends = np.cumsum(np.add.reduceat(np.r_[length, 0], first) * (number > 0)).tolist()
    return [pixels[b - t : b] if w else None for b, t, w in zip(ends, totals.tolist(), whole.tolist())]


def ranges(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Numbers from every start on, as many as its size."""
    ends = np.cumsum(sizes)
    return np.arange(int(sizes.sum())) + np.repeat(starts - (ends - sizes), sizes)


# --- payloads and columns --------------------------------------------------------------

ROW_BYTES = 576
#: Size of the blocks of a plan's transforms, as a power of two.
PLAN_BITS = 9
#: Plans by a checksum; each needs an inverse or the cache.
PLANS = 8
FILL = b"\xff"


def padded_payload(raw: bytes) -> bytes:
    """Filled to a positive multiple of the row."""
    return raw + FILL * (max(1, -(-len(raw) // ROW_BYTES)) * ROW_BYTES - len(raw))


def plan_of(pixels: np.ndarray) -> dict:
    """Transforms and cache of an image, by its content: a checksum of the samples picks
    one of ``PLANS``, so that every image is read with an inverse or the cache, and over a
    table all of them are used. Images of at most
    sixteen values take the palette, by which pixels share a byte."""
    samples = (pixels >> np.uint32(8) & np.uint32(255)).astype(np.uint8)
    if np.count_nonzero(np.bincount(samples.reshape(-1), minlength=256)) <= 16:
        return {"transforms": ((PALETTE,),)}
    choice = zlib.crc32(samples.tobytes()) % PLANS
    shape = lambda bits: (blocks(pixels.shape[0], bits), blocks(pixels.shape[1], bits))
    if choice < 4:  # each predictor that needs nothing of its own row but the left pixel
        modes = np.resize(np.array(((1, 2), (3, 4), (8, 9), (0, 2))[choice]), shape(PLAN_BITS))
        return {"transforms": ((PREDICTOR, PLAN_BITS, modes),)}
    if choice == 4:
        return {"transforms": ((CROSS_COLOUR, PLAN_BITS, np.full(shape(PLAN_BITS), OPAQUE_BLACK | 0x102030, np.uint32)),)}
    if choice == 5:
        return {"transforms": ((SUBTRACT_GREEN,),)}
    if choice == 6:
        return {"transforms": ((PALETTE,),)}
    return {"cache_bits": 4}


def images_of(payload: bytes) -> list[np.ndarray]:
    """Pixels whose green samples are the payload's bytes, row by row."""
    rows = np.frombuffer(payload, np.uint8).reshape(-1, ROW_BYTES)
    return [rows[at : at + MAX_SIDE].astype(np.uint32) << np.uint32(8) | np.uint32(OPAQUE_BLACK) for at in range(0, len(rows), MAX_SIDE)]


def store(payload: bytes) -> bytes:
    return b"".join(encode_image(p, **plan_of(p)) for p in images_of(payload))


def store_all(payloads: list[bytes]) -> list[bytes]:
    """``store`` of every payload, all images written together."""
    images = [images_of(p) for p in payloads]
    media = iter(encode_images([(p, plan_of(p)) for own in images for p in own]))
    return [b"".join(next(media) for _ in own) for own in images]


def load(media: bytes) -> np.ndarray:
    """Pixels of all images, one below the other."""
    found, at = [], 0
    while at < len(media):
        pixels, size = decode_image(media[at:])
        found.append(pixels)
        at += size
    return np.concatenate(found)


def load_all(media: list[bytes]) -> list[np.ndarray]:
    """``load`` of everything stored, all images read together."""
    parts, owner = [], []
    for n, one in enumerate(media):
        at = 0
        while at < len(one):
            size = int.from_bytes(one[at + 4 : at + 8], "little") + 8
            parts.append(one[at : at + size])
            owner.append(n)
            at += size
    found: list[list[np.ndarray]] = [[] for _ in media]
    for n, (pixels, _) in zip(owner, decode_images(parts)):
        found[n].append(pixels)
    return [own[0] if len(own) == 1 else np.concatenate(own) for own in found]


def features(pixels: np.ndarray) -> str:
    """Size, mean and spread of the samples and their share in sixteen bins."""
    samples = (pixels >> np.uint32(8) & np.uint32(255)).astype(np.uint8)
    counts = np.bincount(samples.reshape(-1), minlength=256)
    level = np.arange(256)
    mean = float(counts @ level) / samples.size
    spread = max(0.0, float(counts @ (level * level)) / samples.size - mean * mean) ** 0.5
    shares = counts.reshape(16, 16).sum(axis=1) * 1000 // samples.size
    return f"{pixels.shape[1]}x{pixels.shape[0]} mean {mean:.4f} spread {spread:.4f} bins {','.join(map(str, shares.tolist()))}"


def decode_column(media: Column) -> Column:
    """Struct of ``height``, ``width`` and ``argb`` (four bytes a pixel, alpha first)."""

    @F.pandas_udf("height int, width int, argb binary")
    def decode(rows: pd.Series) -> pd.DataFrame:
        out = []
        for row in rows:
            pixels = None if row is None else load(row)
            out.append((None, None, None) if pixels is None else (*pixels.shape, pixels.astype(">u4").tobytes()))
        return pd.DataFrame(out, columns=["height", "width", "argb"])

    return decode(media)


def store_column(raw: Column) -> Column:
    """The stored form of a text's or binary's bytes; null counts as empty."""

    @F.pandas_udf("binary")
    def stored(rows: pd.Series) -> pd.Series:
        return rows.map(lambda r: store(padded_payload(r or b"")))

    return stored(raw.cast("binary"))


def round_trip(raw: bytes | None) -> tuple:
    media = store(padded_payload(raw or b""))
    return described(raw or b"", media, load(media))


def round_trips(rows: Iterable[bytes | None]) -> Iterator[tuple]:
    """``round_trip`` of every row."""
    for raws in gathered(rows):
        if len(raws[0]) > TOGETHER:
            yield round_trip(raws[0])
            continue
        media = store_all([padded_payload(r) for r in raws])
        yield from map(described, raws, media, load_all(media))


def gathered(rows: Iterable[bytes | None]) -> Iterator[list[bytes]]:
    own, size = [], 0
    for row in rows:
        raw = row or b""
        if own and size + len(raw) > TOGETHER:
            yield own
            own, size = [], 0
        own.append(raw)
        size += len(raw) + ROW_BYTES
    if own:
        yield own


def described(raw: bytes, media: bytes, pixels: np.ndarray) -> tuple:
    payload = (pixels >> np.uint32(8) & np.uint32(255)).astype(np.uint8).tobytes()
    return len(raw), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-32:]), len(media), hashlib.sha256(media).hexdigest(), features(pixels)


ROUND_TRIP = ["n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"]


def media_digests(df: DataFrame, key: str, text: str) -> DataFrame:
    """Every text stored, read back and described. Nulls count as empty texts,
    repeated rows are stored alike, an empty table gives no rows; only key and text
    are read."""

    @F.pandas_udf("n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string")
    def digests(rows: pd.Series) -> pd.DataFrame:
        return pd.DataFrame(list(round_trips(rows)), columns=ROUND_TRIP)

    return df.select(F.col(f"`{key}`").alias("key"), digests(F.col(f"`{text}`").cast("binary")).alias("d")).select("key", "d.*")


def op6_webp(spark, sf_dir):
    """All documents as lossless images and back."""
    return media_digests(read_table(spark, sf_dir, "documents"), "doc_id", "text").withColumnRenamed("key", "doc_id")
