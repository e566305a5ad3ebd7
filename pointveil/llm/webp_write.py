"""Lossless WebP writer: prefix codes fitted to each image, back-references, colour cache and the four transforms."""

from __future__ import annotations

import functools
import math
import re

import numpy as np

from .webp_planes import CACHE_FACTOR, DISTANCES, GREEN, LENGTH_ORDER, LENGTHS, MOST_SIDE, NEAR, SIGNATURE, channels, cross, joined, pack_bits, predict, reversed_bits, reversed_few

#: Longest code of a pixel symbol and of a code length; the format allows 15 and 7.
MOST_CODE, MOST_LENGTH_CODE = 11, 7
#: Longest run of a back-reference, the farthest it reaches, and the shortest that is worth one.
MOST_RUN, MOST_BACK, LEAST_RUN = 4096, (1 << 20) - 120, 3
#: Block size (as a power of two) of the predictor and cross-colour planes that the store writes.
WIDE_BLOCK = 9


#: Runs of code lengths that are told as runs: three zeros or more, or a length and three more of it.
_LONG_RUN = re.compile(rb"\x00{3,}|([^\x00])\1{3,}", re.DOTALL)


class _Out:
    """Bits to come, least significant first: values and their widths, singly or as arrays."""

    def __init__(self):
        self.values, self.widths = [], []
        self.parts: list[tuple[np.ndarray, np.ndarray]] = []

    def put(self, value: int, width: int) -> None:
        self.values.append(value)
        self.widths.append(width)

    def put_list(self, values: list[int], widths: list[int]) -> None:
        self.values += values
        self.widths += widths

    def put_all(self, values: np.ndarray, widths: np.ndarray) -> None:
        self._close()
        self.parts.append((values, widths))

    def _close(self) -> None:
        if self.values:
            self.parts.append((np.array(self.values, dtype=np.int64), np.array(self.widths, dtype=np.int64)))
            self.values, self.widths = [], []

    def all(self) -> tuple[np.ndarray, np.ndarray]:
        """All values and their widths."""
        self._close()
        return tuple(np.concatenate(x) for x in zip(*self.parts)) if len(self.parts) > 1 else self.parts[0]

    def bytes(self) -> bytes:
        values, widths = self.all()
        return _packed_bits(values, widths)[: -(-int(widths.sum()) // 8)]


def _packed_bits(values: np.ndarray, widths: np.ndarray) -> bytes:
    """All bits, in 64-bit words: a value lies in the word of its first bit, and what is over in the next."""
    ends = widths.cumsum()
    start, values = ends - widths, values.astype(np.uint64)
    word, shift = start >> 6, (start & 63).astype(np.uint64)
    heads = np.concatenate([[0], (word[1:] != word[:-1]).nonzero()[0] + 1])
    out = np.zeros((int(ends[-1]) >> 6) + 2, dtype=np.uint64)
    out[word[heads]] = np.bitwise_or.reduceat(values << shift, heads)
    over = ((start & 63) + widths > 64).nonzero()[0]
    out[word[over] + 1] |= values[over] >> (np.uint64(64) - shift[over])
    return out.astype("<u8", copy=False).tobytes()


def code_lengths(counts: np.ndarray, most: int) -> np.ndarray:
    """Lengths of an optimal prefix code for the counts; rare symbols are taken as commoner until none exceeds ``most``."""
    lengths = np.zeros(len(counts), dtype=np.int64)
    used = counts.nonzero()[0]
    if len(used) < 2:
        lengths[used] = 1
        return lengths
    floor = 1
    while True:
        weight = np.maximum(counts[used], floor)
        order = np.argsort(weight, kind="stable")
        depth = _depths(weight[order].tolist())
        if max(depth) <= most:
            lengths[used[order]] = depth
            return lengths
        floor *= 2


def _few_lengths(counts: list[int], most: int) -> list[int]:
    """``code_lengths`` of a small alphabet, without arrays."""
    used = [s for s, n in enumerate(counts) if n]
    lengths, floor = [0] * len(counts), 1
    if len(used) < 2:
        for s in used:
            lengths[s] = 1
        return lengths
    while True:
        order = sorted(used, key=lambda s: max(counts[s], floor))
        depth = _depths([max(counts[s], floor) for s in order])
        if max(depth) <= most:
            for s, d in zip(order, depth):
                lengths[s] = d
            return lengths
        floor *= 2


def _few_codes(lengths: list[int]) -> tuple[list[int], list[int]]:
    """``_codes`` of a small alphabet, without arrays."""
    used = sorted((n, s) for s, n in enumerate(lengths) if n)
    bits, widths = [0] * len(lengths), [0] * len(lengths)
    if len(used) < 2:
        return bits, widths
    most, at = used[-1][0], 0
    order = reversed_few(most)
    for n, s in used:
        bits[s], widths[s] = order[at], n
        at += 1 << (most - n)
    return bits, widths


def _depths(weights: list[int]) -> list[int]:
    """Leaf depths of a tree of least weighted length over ascending weights (leaves and inner nodes as two queues)."""
    n = len(weights)
    total = weights + [0] * (n - 1)
    parent = [0] * (2 * n - 1)
    leaf, inner = 0, n
    for new in range(n, 2 * n - 1):
        weight = 0
        for _ in range(2):
            if leaf < n and (inner >= new or total[leaf] <= total[inner]):
                one, leaf = leaf, leaf + 1
            else:
                one, inner = inner, inner + 1
            parent[one] = new
            weight += total[one]
        total[new] = weight
    depth = [0] * (2 * n - 1)
    for i in range(2 * n - 3, -1, -1):
        depth[i] = depth[parent[i]] + 1
    return depth[:n]


def _codes(lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(bits in stream order, width) by symbol; the only symbol of a code takes no bits."""
    bits, widths = np.zeros(len(lengths), dtype=np.int64), np.zeros(len(lengths), dtype=np.int64)
    used = lengths.nonzero()[0]
    if len(used) < 2:
        return bits, widths
    used = used[np.argsort(lengths[used].astype(np.uint8), kind="stable")]
    size = lengths[used]
    room = 1 << (size[-1] - size)
    bits[used], widths[used] = reversed_bits(int(size[-1]))[room.cumsum() - room], size
    return bits, widths


def _runs(lengths: np.ndarray) -> tuple[list[int], list[int], list[int]]:
    """(symbols, extra bits, their numbers) of the run-length coded code lengths, without the last zeros."""
    kept = lengths.astype(np.uint8).tobytes().rstrip(b"\0")
    symbols: list[int] = []
    extra: list[tuple[int, int, int]] = []
    done = 0
    for found in _LONG_RUN.finditer(kept):
        start, stop = found.span()
        value = kept[start]
        symbols += kept[done : start + (value > 0)]
        times, done = stop - start - (value > 0), stop
        while times > 2:
            kind, least, most, n = (16, 3, 6, 2) if value else (18, 11, 138, 7) if times > 10 else (17, 3, 10, 3)
            now = min(times, most)
            extra.append((len(symbols), now - least, n))
            symbols.append(kind)
            times -= now
        if times:
            symbols += [value] * times
    symbols += kept[done:]
    bits, sizes = [0] * len(symbols), [0] * len(symbols)
    for at, more, n in extra:
        bits[at], sizes[at] = more, n
    return symbols, bits, sizes


@functools.lru_cache(maxsize=256)
def _distance_code(counts: bytes) -> "Code":
    """The code of distance counts, which are few and often the same."""
    return Code(np.frombuffer(counts, dtype=np.int64))


class Code:
    """The prefix code fitted to symbol counts: ``bits`` and ``widths`` by symbol, and its own description."""

    def __init__(self, counts: np.ndarray):
        lengths = code_lengths(counts, MOST_CODE)
        self.bits, self.widths = _codes(lengths)
        used = lengths.nonzero()[0].tolist() or [0]
        if len(used) <= 2 and used[-1] < 256:
            wide = used[0] > 1
            self.told = [1, len(used) - 1, int(wide), *used], [1, 1, 1, 8 if wide else 1, 8][: 3 + len(used)]
            return
        symbols, extra, sizes = _runs(lengths)
        counted = [0] * 19
        for s in symbols:
            counted[s] += 1
        by_order = _few_lengths(counted, MOST_LENGTH_CODE)
        in_order = [by_order[s] for s in LENGTH_ORDER]
        kinds = 19
        while kinds > 4 and not in_order[kinds - 1]:
            kinds -= 1
        size = max(2, (len(symbols) - 2).bit_length())  # the number of runs is told, so the last zeros need none
        size += size & 1
        bits, widths = _few_codes(by_order)
        self.told = (
            [0, kinds - 4, *in_order[:kinds], 1, (size - 2) // 2, len(symbols) - 2, *[bits[s] | e << widths[s] for s, e in zip(symbols, extra)]],
            [1, 4, *[3] * kinds, 1, 3, size, *[widths[s] + n for s, n in zip(symbols, sizes)]],
        )


def _last_equal(words: np.ndarray, image: np.ndarray | None = None) -> np.ndarray:
    """The last earlier position of the same word, or -1; ``image`` parts the pixels of several images."""
    keys = words.astype(np.uint64) << np.uint64(32)
    keys |= np.arange(len(words), dtype=np.uint64)
    keys.sort()
    order, key = (keys & np.uint64(0xFFFFFFFF)).astype(np.int64), keys >> np.uint64(32)
    same = key[1:] == key[:-1]
    if image is not None:
        same &= image[order[1:]] == image[order[:-1]]
    same = same.nonzero()[0]
    out = np.full(len(words), -1, dtype=np.int64)
    out[order[same + 1]] = order[same]
    return out


def slots_of(argb: np.ndarray, cache: int) -> np.ndarray:
    """Cache slots of colours."""
    return (argb * np.uint32(CACHE_FACTOR)) >> np.uint32(32 - cache)


def cover(argb: np.ndarray, cache: int, refs: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(position, run, distance, cache slot) of symbols that make up the pixels: run 0 is a literal, a cached colour
    has a slot (else -1); a back-reference goes to the last place where its first pixel stood, if enough follow."""
    n = len(argb)
    return cover_all(argb, cache, refs, np.array([n]), np.zeros(n, dtype=np.int64), _last_equal(argb))


def cover_all(argb: np.ndarray, cache: int, refs: bool, ends: np.ndarray, image: np.ndarray, before: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """``cover`` of images one after the other that end at ``ends``; ``before``: the last earlier position of every pixel's colour."""
    n = len(argb)
    starts, runs, backs, covered = [], [], [], np.zeros(n, dtype=bool)
    if refs:
        i = (before >= 0).nonzero()[0]
        size = np.diff(ends, prepend=0)
        i = i[(i + LEAST_RUN <= ends[image[i]]) & (size[image[i]] > LEAST_RUN)]
        for k in range(1, LEAST_RUN):
            i = i[argb[i + k] == argb[before[i] + k]]
        i = i[i - before[i] <= MOST_BACK]
        pixels, end = argb.tolist() if len(i) else [], 0
        for at, back, last in zip(i.tolist(), (i - before[i]).tolist(), ends[image[i]].tolist()):
            if at < end:
                continue
            end = at + LEAST_RUN
            stop = min(last, at + MOST_RUN)
            while end < stop and pixels[end] == pixels[end - back]:
                end += 1
            starts.append(at)
            runs.append(end - at)
            backs.append(back)
            covered[at + 1 : end] = True
    position = (~covered).nonzero()[0]
    run, distance = np.zeros(n, dtype=np.int64), np.zeros(n, dtype=np.int64)
    run[starts], distance[starts] = runs, backs
    slot = np.full(n, -1, dtype=np.int64)
    if cache:
        hashed = slots_of(argb, cache)
        hit = (before >= 0) & (_last_equal(hashed, image) == before) & (run == 0)
        slot[hit] = hashed[hit]
    return position, run[position], distance[position], slot[position]


def _split(value: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(symbol, extra bits, their number) of lengths or distances."""
    if not len(value):
        return value, value, value
    v = np.maximum(value - 1, 0)
    top = np.frexp(v.astype(np.float64))[1].astype(np.int64) - 1
    more = np.where(v < 4, 0, top - 1)
    symbol = np.where(v < 4, v, 2 * top + (v >> np.maximum(more, 0) & 1))
    return symbol, v & ((1 << more) - 1), more


@functools.lru_cache(maxsize=64)
def _near_codes(width: int) -> np.ndarray:
    """Distance codes of short distances: the plane's code where it has one."""
    near = np.arange(8 * width + 9) + len(NEAR)
    for k, (x, y) in reversed(list(enumerate(NEAR))):
        if x + y * width > 0:
            near[x + y * width] = k + 1
    return near


def _distance_codes(far: np.ndarray, width: int) -> np.ndarray:
    near = _near_codes(width)
    return np.where(far < len(near), near[np.minimum(far, len(near) - 1)], far + len(NEAR))


def write_many(images: list[tuple[_Out, np.ndarray, int]], cache: int) -> list[bytes]:
    """Bit streams of images (``headed``), each ended by the entropy-coded main image that ``write_pixels`` gives with
    back-references and a cache: symbols, counts and bits of all images are made together, codes one by one."""
    n, argb = len(images), np.concatenate([x[1] for x in images])
    sizes = np.array([len(x[1]) for x in images])
    of_pixel = np.repeat(np.arange(n), sizes)
    position, run, distance, slot = cover_all(argb, cache, True, sizes.cumsum(), of_pixel, _last_equal(argb, of_pixel))
    image = of_pixel[position]
    b, g, r, a = argb.take(position).astype("<u4", copy=False).view(np.uint8).reshape(-1, 4).T.astype(np.int64, order="C")
    literal, ref, cached = ((run == 0) & (slot < 0)).nonzero()[0], run.nonzero()[0], (slot >= 0).nonzero()[0]
    width, far = np.array([x[2] for x in images])[image[ref]], distance[ref]
    for w in np.unique(width).tolist():
        far[width == w] = _distance_codes(far[width == w], w)
    (size, size_bits, size_n), (reach, reach_bits, reach_n) = _split(run[ref]), _split(far)
    first = g.copy()
    first[cached], first[ref] = GREEN + LENGTHS + slot[cached], GREEN + size
    alphabet = GREEN + LENGTHS + (1 << cache)
    first += image * alphabet
    of_literal, reach = image[literal] * 256, reach + image[ref] * DISTANCES
    samples = [c.take(literal) + of_literal for c in (r, b, a)]
    counted = [np.bincount(x, minlength=n * m).reshape(n, m) for x, m in ((first, alphabet), *[(x, 256) for x in samples], (reach, DISTANCES))]
    bits, widths = [np.empty(x.shape, dtype=np.int64) for x in counted], [np.empty(x.shape, dtype=np.int64) for x in counted]
    for i, (out, _, _) in enumerate(images):
        out.put_list([1, cache, 0], [1, 4, 1])
        three = [c[i] for c in counted[1:4]]
        if _alike(three, int(three[0].sum())):
            codes = [Code(three[0] + three[1] + three[2])] * 3
        else:
            codes = [Code(c) for c in three]
        for k, code in enumerate((Code(counted[0][i]), *codes, _distance_code(counted[4][i].tobytes()))):
            out.put_list(*code.told)
            bits[k][i], widths[k][i] = code.bits, code.widths
    bits, widths = [x.ravel() for x in bits], [x.ravel() for x in widths]
    word, wide = bits[0].take(first), widths[0].take(first)
    now, n_now = word.take(literal), wide.take(literal)
    for x, b, w in zip(samples, bits[1:4], widths[1:4]):
        now |= b.take(x) << n_now
        n_now += w.take(x)
    word[literal], wide[literal] = now, n_now
    now, n_now = word[ref], wide[ref]
    for more, m in ((size_bits, size_n), (bits[4].take(reach), widths[4].take(reach)), (reach_bits, reach_n)):
        now |= more << n_now
        n_now += m
    word[ref], wide[ref] = now, n_now
    # every image: what stands before its symbols, the symbols, and nothing up to the next word of 64 bits
    heads = [out.all() for out, _, _ in images]
    head_n, symbols_n = np.array([len(v) for v, _ in heads]), np.bincount(image, minlength=n)
    head_width = np.concatenate([w for _, w in heads])
    own = np.repeat(np.arange(n), head_n)
    used = np.bincount(own, head_width, n).astype(np.int64) + np.bincount(image, wide, n).astype(np.int64)
    start = (head_n + symbols_n + 1).cumsum() - (head_n + symbols_n + 1)
    values, sizes = np.zeros(int((head_n + symbols_n + 1).sum()), dtype=np.int64), np.empty(int((head_n + symbols_n + 1).sum()), dtype=np.int64)
    at_head = np.arange(len(own)) + (start - (head_n.cumsum() - head_n))[own]
    at_symbol = np.arange(len(image)) + (start + head_n - (symbols_n.cumsum() - symbols_n))[image]
    values[at_head], sizes[at_head] = np.concatenate([v for v, _ in heads]), head_width
    values[at_symbol], sizes[at_symbol] = word, wide
    sizes[start + head_n + symbols_n] = -used % 64
    packed, ends = _packed_bits(values, sizes), (used + -used % 64).cumsum() // 8
    return [packed[e - (-(-u // 64) * 8) : e - (-(-u // 64) * 8) + -(-u // 8)] for e, u in zip(ends.tolist(), used.tolist())]


def _alike(counts: list[np.ndarray], n: int) -> bool:
    """Whether one code suits the three channels: their histograms of ``n`` samples are about as far apart as chance has it."""
    r, b, a = counts
    return int(np.abs(r - b).sum() + np.abs(b - a).sum()) <= 1.2 * n


def write_pixels(out: _Out, argb: np.ndarray, width: int, cache: int = 0, refs: bool = False, main: bool = False, groups: int = 1, block: int = 2) -> None:
    """An entropy-coded image; ``groups`` deals the rows of blocks to so many code groups in turn (main image only)."""
    out.put(int(cache > 0), 1)
    if cache:
        out.put(cache, 4)
    position, run, distance, slot = cover(argb, cache, refs)
    of_symbol = np.zeros(len(position), dtype=np.int64)
    if main:
        out.put(int(groups > 1), 1)
    if groups > 1:
        high, across = -(-(len(argb) // width) >> block), -(-width >> block)
        groups = min(groups, high)
        out.put(block - 2, 3)
        write_pixels(out, joined(0, 0, np.repeat(np.arange(high) % groups, across), 0), across)
        of_symbol = (position // width >> block) % groups
    b, g, r, a = argb.take(position).astype("<u4", copy=False).view(np.uint8).reshape(-1, 4).T.astype(np.int64, order="C")
    literal, ref, cached = ((run == 0) & (slot < 0)).nonzero()[0], run.nonzero()[0], (slot >= 0).nonzero()[0]
    far = _distance_codes(distance[ref], width)
    (size, size_bits, size_n), (reach, reach_bits, reach_n) = _split(run[ref]), _split(far)
    first = g.copy()
    first[cached], first[ref] = GREEN + LENGTHS + slot[cached], GREEN + size
    # bits and width of every symbol; its four parts are at most 50 bits together
    word, width_of = np.zeros(len(position), dtype=np.int64), np.zeros(len(position), dtype=np.int64)
    alphabet = GREEN + LENGTHS + (1 << cache if cache else 0)
    for group in range(groups):
        if groups > 1:
            mine = (of_symbol == group).nonzero()[0]
            plain, to = (of_symbol[literal] == group).nonzero()[0], (of_symbol[ref] == group).nonzero()[0]
            plain = literal[plain]
        else:
            mine, plain, to = slice(None), literal, slice(None)
        samples = [c.take(plain) for c in (r, b, a)]
        counts = [np.bincount(c, minlength=256) for c in samples]
        code = Code(np.bincount(first[mine], minlength=alphabet))
        out.put_list(*code.told)
        word[mine], width_of[mine] = code.bits.take(first[mine]), code.widths.take(first[mine])
        codes = [Code(counts[0] + counts[1] + counts[2])] * 3 if _alike(counts, int(counts[0].sum())) else [Code(c) for c in counts]
        bits, wide = word.take(plain), width_of.take(plain)
        for c, code in zip(samples, codes):
            out.put_list(*code.told)
            bits |= code.bits.take(c) << wide
            wide += code.widths.take(c)
        word[plain], width_of[plain] = bits, wide
        code = Code(np.bincount(reach[to], minlength=DISTANCES))
        out.put_list(*code.told)
        bits, wide = word[ref[to]], width_of[ref[to]]
        for more, n in ((size_bits[to], size_n[to]), (code.bits[reach[to]], code.widths[reach[to]]), (reach_bits[to], reach_n[to])):
            bits |= more << wide
            wide += n
        word[ref[to]], width_of[ref[to]] = bits, wide
    out.put_all(word, width_of)


def encode(pixels: np.ndarray, palette: bool = False, predictor: int | None = None, cross_colour: tuple[int, int, int] | None = None,
           green: bool = False, cache: int = 0, refs: bool = False, block: int = 2, riff: bool = True, groups: int = 1) -> bytes:
    """A lossless WebP file of (height, width, 4) A, R, G, B bytes.

    palette: colour table, at most 256 colours. predictor: one mode for all blocks. cross_colour: (green to red, green
    to blue, red to blue) factors. green: subtract green. cache: colour-cache bits. refs: back-references. groups:
    code groups.
    """
    out, argb, stored = headed(pixels, palette, predictor, cross_colour, green, block)
    write_pixels(out, argb, stored, cache, refs, True, groups, block)
    return filed(out.bytes()) if riff else out.bytes()


def filed(body: bytes) -> bytes:
    """The file of a bit stream."""
    padded = body + b"\0" * (len(body) & 1)
    return b"RIFF" + (12 + len(padded)).to_bytes(4, "little") + b"WEBPVP8L" + len(body).to_bytes(4, "little") + padded


def headed(pixels: np.ndarray, palette: bool = False, predictor: int | None = None, cross_colour: tuple[int, int, int] | None = None,
           green: bool = False, block: int = 2) -> tuple[_Out, np.ndarray, int]:
    """(stream up to the main image, the main image's pixels, their width)."""
    height, width = pixels.shape[:2]
    if not (1 <= width <= MOST_SIDE and 1 <= height <= MOST_SIDE):
        raise ValueError("a side must be 1 to 16384")
    out = _Out()
    for value, n in ((SIGNATURE, 8), (width - 1, 14), (height - 1, 14), (1, 1), (0, 3)):
        out.put(value, n)
    argb, stored = np.ascontiguousarray(pixels).view(">u4").ravel().astype("<u4"), width
    if palette:
        table, index = np.unique(argb, return_inverse=True)
        if len(table) > 256:
            raise ValueError("too many colours for a palette")
        out.put(1, 1), out.put(3, 2), out.put(len(table) - 1, 8)
        write_pixels(out, _steps(table), len(table))
        argb, stored = _packed(index, width, len(table))
    small = (-(-stored >> block)) * (-(-height >> block))
    if predictor is not None:
        modes = np.full(small, 0xFF000000 | predictor << 8, dtype=np.uint32)
        out.put(1, 1), out.put(0, 2), out.put(block - 2, 3)
        write_pixels(out, modes, -(-stored >> block))
        argb = predict(argb, stored, block, modes, False)
    if cross_colour is not None:
        factors = np.full(small, _factor_word(cross_colour), dtype=np.uint32)
        out.put(1, 1), out.put(1, 2), out.put(block - 2, 3)
        write_pixels(out, factors, -(-stored >> block))
        argb = cross(argb, stored, block, factors, False)
    if green:
        out.put(1, 1), out.put(2, 2)
        argb = _less_green(argb)
    out.put(0, 1)
    return out, argb, stored


def _steps(table: np.ndarray) -> np.ndarray:
    return joined(*[np.diff(np.concatenate([[0], c])) for c in channels(table)])


def _packed(index: np.ndarray, width: int, colours: int) -> tuple[np.ndarray, int]:
    """(pixels, their width) of palette indices, several in one green byte where there are few colours."""
    index = index.reshape(-1, width)
    packed = pack_bits(colours)
    n, stored = 8 >> packed, -(-width >> packed)
    index = np.pad(index, ((0, 0), (0, (stored << packed) - width))).reshape(len(index), stored, 1 << packed)
    return joined(255, 0, (index << (n * np.arange(1 << packed))).sum(axis=2).ravel(), 0), stored


def _factor_word(factors: tuple[int, int, int]) -> int:
    return 0xFF000000 | (factors[2] & 255) << 16 | (factors[1] & 255) << 8 | factors[0] & 255


def _less_green(argb: np.ndarray) -> np.ndarray:
    a, r, g, b = channels(argb)
    return joined(a, r - g, g, b - g)


# ---------------------------------------------------------------- choosing transforms


#: n log2 n of the first counts.
_N_LOG_N = np.concatenate([[0.0], np.arange(1, 1 << 16) * np.log2(np.arange(1, 1 << 16))])


def _costs(parts: list[np.ndarray]) -> list[float]:
    """Bits of each part's 8-bit samples under one code."""
    counts = np.stack([np.bincount(x.ravel(), minlength=256) for x in parts])
    sizes = [x.size for x in parts]
    each = _N_LOG_N[counts] if max(sizes) < len(_N_LOG_N) else counts * np.log2(np.maximum(counts, 1))
    return [n * math.log2(max(1, n)) - bits for n, bits in zip(sizes, each.sum(axis=1).tolist())]


def cost_of(samples: np.ndarray) -> float:
    """``_costs`` of one part."""
    return _costs([samples])[0]


def factors_of(n: int, sums: list[int], products: list[int]) -> tuple[int, int, int]:
    """Cross-colour factors (32nds) that take most of red and blue off by signed green; 0 where that is under a tenth.

    sums: of red, green, blue; products: of green and green, red and green, blue and green, red and red, blue and blue.
    """
    r, g, b = sums
    spread, out = float(n * products[0] - g * g), []
    for both, own, x in ((products[1], products[3], r), (products[2], products[4], b)):
        common, own = float(n * both - x * g), float(n * own - x * x)
        out.append(max(-128, min(127, round(32 * common / spread))) if common * common > 0.1 * spread * own else 0)
    return out[0], out[1], 0


def _slopes(p: np.ndarray) -> tuple[int, int, int]:
    """``factors_of`` of pixels."""
    c = p[:, 1:].T.copy().view(np.int8).astype(np.int64)
    return factors_of(len(p), c.sum(axis=1).tolist(), (c[[1, 0, 2, 0, 2]] * c[[1, 1, 1, 0, 2]]).sum(axis=1).tolist())


def cross_left(p: np.ndarray, width: int, factors: tuple[int, int, int]) -> np.ndarray:
    """Samples that the cross-colour factors leave."""
    argb = p[:, ::-1].copy().view("<u4").ravel()
    left = cross(argb, width, WIDE_BLOCK, np.full((len(p) // (width << WIDE_BLOCK) + 1) * (-(-width >> WIDE_BLOCK)), _factor_word(factors), dtype=np.uint32), False)
    return left.view(np.uint8).reshape(-1, 4)


def palette_cost(p: np.ndarray, width: int) -> float:
    """Bits of a palette of the pixels and of its indices."""
    table, index = np.unique(p.view("<u4").ravel(), return_inverse=True)
    steps = np.diff(np.concatenate([[[0] * 4], table.view(np.uint8).reshape(-1, 4)]), axis=0) & 255
    return 200 + cost_of(steps) + cost_of(channels(_packed(index, width, len(table))[0])[2])


def chosen(pixels: np.ndarray, cache: int) -> dict:
    """Options of ``encode`` that cost an image least by estimate: a palette, one predictor, cross-colour or subtracted
    green, or none of them; ties go to the earlier of them."""
    width = pixels.shape[1]
    p = np.ascontiguousarray(pixels.reshape(-1, 4))
    alike = p.copy()
    alike[:, 1::2] -= p[:, 2:3]
    tried = [({}, 0, p), ({"green": True}, 0, alike)]
    flat = p.ravel()
    for mode, step in ((1, 4), (2, 4 * width)):
        if len(flat) > step:  # the first pixels, which look elsewhere, are left out of the estimate
            tried.append(({"predictor": mode}, 100 + 8 * step, flat[step:] - flat[:-step]))
    factors = _slopes(p)
    if any(factors):
        tried.append(({"cross_colour": factors}, 100, cross_left(p, width, factors)))
    choices = [(options, more + bits) for (options, more, _), bits in zip(tried, _costs([x for _, _, x in tried]))]
    words = np.sort(p.view("<u4").ravel())
    if np.count_nonzero(words[1:] != words[:-1]) < 256:
        choices.append(({"palette": True}, palette_cost(p, width)))
    best = min(choices, key=lambda c: c[1])[0]
    return {**best, "cache": cache, "refs": True, "block": WIDE_BLOCK}
