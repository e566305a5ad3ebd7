"""Lossless WebP reader: the whole bit stream of the format.

Prefix codes (simple, normal, run-length coded lengths) become lookup tables, so one look gives a symbol and its
length. With one code group the symbols are found by looking at every bit position of a stretch at once: where a
symbol that began there would end. The real symbols are then followed from end to start, back-references are read on
the way, and pixels of references and of the colour cache are traced to the literals they repeat. Images with several
code groups (an entropy image) go symbol by symbol. The plane distance map and the four transforms serve both.
"""

from __future__ import annotations

import functools

import numpy as np

from .webp_planes import CACHE_FACTOR, DISTANCES, GREEN, LENGTH_ORDER, LENGTHS, NEAR, SIGNATURE, channels, cross, joined, pack_bits, predict, reversed_bits, reversed_few

#: Marks entries of the green code that are no literals.
OTHER = 1 << 40
#: Bit positions that are looked at together, and the most bits of a pixel's four codes.
STRETCH, MOST_SYMBOL = 1 << 16, 4 * 15
_EIGHT = np.arange(8)


class Bits:
    """Little-endian bit reader over 64-bit words that start at every byte."""

    def __init__(self, data: bytes):
        self.data, self.at, self.end = data, 0, 8 * len(data)
        self.padded = data + bytes(32)
        self.words = np.ndarray(len(data) + 8, dtype="<u8", buffer=self.padded, strides=(1,)).tolist()

    @functools.cached_property
    def raw(self) -> np.ndarray:
        """The 32 bits from every byte on."""
        return np.ndarray(len(self.data) + 24, dtype="<u4", buffer=self.padded, strides=(1,)).astype(np.int64)

    def read(self, n: int) -> int:
        """The next ``n`` (at most 24) bits."""
        at = self.at
        self.at = at + n
        if self.at > self.end:
            raise ValueError("the bit stream is too short")
        return self.words[at >> 3] >> (at & 7) & ((1 << n) - 1)


    def same(self, start: int, n: int) -> bool:
        """Whether the next ``n`` bits are those that begin at ``start``."""
        return self.at + n <= self.end and self._cut(start, n) == self._cut(self.at, n)

    def _cut(self, at: int, n: int) -> int:
        return int.from_bytes(self.data[at >> 3 : (at + n >> 3) + 1], "little") >> (at & 7) & ((1 << n) - 1)


class Prefix:
    """One prefix code: symbols of equal length ascend, shorter codes first; bits come most significant first.

    ``symbols`` and ``sizes`` list, by the next ``depth`` bits, the symbol that begins there and its code's length.
    """

    def __init__(self, lengths: bytes):
        size = np.frombuffer(lengths, dtype=np.uint8)
        used = size.nonzero()[0]
        if len(used) == 1:
            self.depth, self.symbols, self.sizes = 0, used, np.zeros(1, dtype=np.int64)
            return
        used = used[np.argsort(size[used], kind="stable")]
        width = size[used].astype(np.int64)
        if not len(used) or (1 << (15 - width)).sum() != 1 << 15:
            raise ValueError("a prefix code is not complete")
        self.depth = int(width[-1])
        room = 1 << (self.depth - width)
        at = np.repeat(np.arange(len(used)), room).take(reversed_bits(self.depth))
        self.symbols, self.sizes = used.take(at), width.take(at)

    def table(self, shift: int) -> tuple[list[int], int]:
        """(entries by the next bits, mask of these bits): the symbol at ``shift``, then four bits of length."""
        return (self.symbols << (shift + 4) | self.sizes).tolist(), (1 << self.depth) - 1

    def green_table(self) -> tuple[list[int], int]:
        """As ``table(8)`` for literals; others are marked and not shifted."""
        entry = np.where(self.symbols < GREEN, self.symbols << 12, OTHER | self.symbols << 4) | self.sizes
        return entry.tolist(), (1 << self.depth) - 1


def _prefix(bits: Bits, alphabet: int) -> Prefix:
    lengths = bytearray(alphabet)
    if bits.read(1):  # one or two symbols
        two = bits.read(1)
        lengths[bits.read(8 if bits.read(1) else 1)] = 1
        if two:
            lengths[bits.read(8)] = 1
        return _code(bytes(lengths))
    of_lengths = bytearray(19)
    for i in range(4 + bits.read(4)):
        of_lengths[LENGTH_ORDER[i]] = bits.read(3)
    most = 2 + bits.read(2 + 2 * bits.read(3)) if bits.read(1) else alphabet
    table, mask = _length_table(bytes(of_lengths))
    words, pos, at, previous = bits.words, bits.at, 0, 8
    while at < alphabet and most:
        most -= 1
        word = words[pos >> 3] >> (pos & 7)
        entry = table[word & mask]
        n, s = entry & 15, entry >> 4
        pos += n
        if s < 16:
            lengths[at] = s
            at += 1
            if s:
                previous = s
            continue
        word >>= n
        if s == 16:
            value, times, n = previous, 3 + (word & 3), 2
        elif s == 17:
            value, times, n = 0, 3 + (word & 7), 3
        else:
            value, times, n = 0, 11 + (word & 127), 7
        pos += n
        if at + times > alphabet:
            raise ValueError("code lengths overflow the alphabet")
        if value:
            lengths[at : at + times] = bytes((value,)) * times
        at += times
    bits.at = pos
    if pos > bits.end:
        raise ValueError("the bit stream is too short")
    return _code(bytes(lengths))


@functools.lru_cache(maxsize=64)
def _code(lengths: bytes) -> Prefix:
    return Prefix(lengths)


@functools.lru_cache(maxsize=64)
def _length_table(lengths: bytes) -> tuple[list[int], int]:
    """As ``Prefix.table(0)``, without arrays: these codes have few symbols of at most seven bits."""
    used = sorted((n, s) for s, n in enumerate(lengths) if n)
    if len(used) == 1:
        return [used[0][1] << 4], 0
    depth = used[-1][0] if used else 0
    if not used or sum(1 << (depth - n) for n, _ in used) != 1 << depth:
        raise ValueError("a prefix code is not complete")
    order, table, at = reversed_few(depth), [0] * (1 << depth), 0
    for n, s in used:
        room = 1 << (depth - n)
        table[order[at] :: 1 << n] = [s << 4 | n] * room
        at += room
    return table, (1 << depth) - 1


def _group(bits: Bits, cache: int) -> list[Prefix]:
    """One code group: green, red, blue, alpha, distance."""
    green = _prefix(bits, GREEN + LENGTHS + (1 << cache if cache else 0))
    start = bits.at
    three = [_prefix(bits, 256)]
    told = bits.at - start
    for _ in range(2):  # the same bits tell the same code
        if bits.same(start, told):
            three.append(three[0])
            bits.at += told
        else:
            three.append(_prefix(bits, 256))
    return [green, *three, _prefix(bits, DISTANCES)]


def _tables(group: list[Prefix]) -> tuple:
    green, red, blue, alpha, distance = group
    return *green.green_table(), *red.table(16), *blue.table(0), *alpha.table(24), *distance.table(0)


def extra_of(symbol: int, bits: Bits) -> int:
    """The value of a length or distance symbol."""
    if symbol < 4:
        return symbol + 1
    more = (symbol - 2) >> 1
    return ((2 + (symbol & 1)) << more) + bits.read(more) + 1


def plane_of(code: int, width: int) -> int:
    if code > len(NEAR):
        return code - len(NEAR)
    x, y = NEAR[code - 1]
    return max(1, x + y * width)


def _cache_of(bits: Bits) -> int:
    cache = bits.read(4) if bits.read(1) else 0
    if cache > 11:
        raise ValueError("the colour cache is too large")
    return cache


def group_of(bits: Bits) -> tuple[int, list[Prefix] | None]:
    """(cache bits, codes) of a main image with one code group; no codes are read if there are more."""
    cache = _cache_of(bits)
    return cache, None if bits.read(1) else _group(bits, cache)


def read_pixels(bits: Bits, width: int, height: int, main: bool, tally: dict[str, int] | None = None, codes: tuple[int, list[Prefix]] | None = None) -> np.ndarray:
    """ARGB words of an entropy-coded image; ``tally`` counts the literals, back-references and cached colours.
    ``codes``: what ``group_of`` has read already."""
    cache = codes[0] if codes else _cache_of(bits)
    block, of_block, groups_n = 0, None, 1
    if main and not codes and bits.read(1):
        block = bits.read(3) + 2
        of_block = ((read_pixels(bits, -(-width >> block), -(-height >> block), False) >> np.uint32(8)) & np.uint32(0xFFFF)).tolist()
        groups_n = max(of_block) + 1
    groups = [codes[1]] if codes else [_group(bits, cache) for _ in range(groups_n)]
    try:
        if of_block is None:
            out = _read_stretches(bits, groups[0], width, width * height, cache, tally)
        else:
            out = _read_symbols(bits, [_tables(g) for g in groups], width, width * height, cache, block, of_block, tally)
    except IndexError as e:
        raise ValueError("the bit stream is too short") from e
    if bits.at > bits.end:
        raise ValueError("the bit stream is too short")
    return np.array(out, dtype=np.uint32)


def _read_stretches(bits: Bits, group: list[Prefix], width: int, total: int, cache: int, tally: dict[str, int] | None) -> np.ndarray:
    """The pixels of an image with one code group."""
    sizes = [p.sizes for p in group[:4]]
    masks = [(1 << p.depth) - 1 for p in group]
    literal = group[0].symbols < GREEN
    refers = ~literal & (group[0].symbols < GREEN + LENGTHS)
    kind = np.where(literal, 0, 1 + refers)
    distance, distance_m = group[4].table(0)
    some = bool(refers.any())
    value, slot = np.zeros(total, dtype=np.int64), np.full(total, -1, dtype=np.int64)
    copies: list[tuple[int, int, int]] = []
    at, done, words = bits.at, 0, bits.words
    while done < total:
        if at > bits.end:
            raise ValueError("the bit stream is too short")
        span = min(STRETCH, bits.end - at + 1)
        # the next 16 bits of every position from ``at``, and some beyond for symbols that begin inside the stretch
        first = at >> 3
        bytes_n = min(len(bits.raw) - first, (span + 64 >> 3) + 2)
        looks = (bits.raw[first : first + bytes_n, None] >> _EIGHT).ravel()[at & 7 :]
        # where a symbol ends, by where its green code ends: after a literal three channels follow, after a cached
        # colour nothing; a reference is marked by -1, and past the stretch no symbol begins
        n = len(looks)
        spots, follow = np.arange(n), None
        chain = np.empty((2 + some) * n, dtype=np.int64)
        chain[n : 2 * n], chain[2 * n :] = spots, -1
        for k in (1, 2, 3):
            if k == 1 or group[k] is not group[k - 1]:
                one = spots + sizes[k].take(looks & masks[k])
            follow = one if follow is None else one.take(follow, mode="clip", out=chain[:n] if k == 3 else None)
        index = looks[:span] & masks[0]
        ends = np.full(span + MOST_SYMBOL, -1)
        ends[:span] = chain.take(spots[:span] + (sizes[0] + n * kind).take(index))
        seen: list[int] = []
        see, here, left, held = seen.append, 0, total - done, done
        gaps: list[tuple[int, int]] = []
        if ends[0] == 0:  # the only symbol takes no bits
            seen, left = [0] * left, 0
        step = memoryview(ends)
        while left > 0:
            had = len(seen)
            while (go := step[here]) >= 0:
                see(here)
                here = go
            left -= len(seen) - had
            if left < 0:  # bits after the last pixel
                here = seen[left]
                del seen[left:]
                left = 0
            if not left or here >= span:
                break
            look = index[here]
            bits.at = at + here + int(sizes[0][look])
            symbol = int(group[0].symbols[look])
            run = extra_of(symbol - GREEN, bits)
            d = distance[words[bits.at >> 3] >> (bits.at & 7) & distance_m]
            bits.at += d & 15
            back = plane_of(extra_of(d >> 4, bits), width)
            pos = total - left
            if back > pos or run > left:
                raise ValueError("a back-reference leaves the image")
            copies.append((pos, run, back))
            gaps.append((len(seen), run))
            left -= run
            here = bits.at - at
        if seen:
            where = np.fromiter(seen, np.int64, len(seen))
            spot = held + np.arange(len(seen))
            for count, run in gaps:
                spot[count:] += run
            _place(looks, where, group, masks, literal, cache, spot, value, slot)
        done = total - left
        at += here
    bits.at = at
    if tally is not None:
        copied = sum(run for _, run, _ in copies)
        cached = int((slot >= 0).sum())
        for name, count in (("literals", total - copied - cached), ("references", len(copies)), ("cached", cached)):
            tally[name] = tally.get(name, 0) + count
    return traced(value, slot, copies, cache)


def _place(looks, where, group, masks, literal, cache, spot, value, slot) -> None:
    """Values of the literals and slots of the cached colours that begin at the bits ``where``."""
    index = looks.take(where) & masks[0]
    symbol, is_literal = group[0].symbols.take(index), literal.take(index)
    lit = is_literal.nonzero()[0]
    at, pixel = (where + group[0].sizes.take(index)).take(lit), symbol.take(lit) << 8
    for prefix, mask, shift in zip(group[1:4], masks[1:4], (16, 0, 24)):
        index = looks.take(at) & mask
        pixel |= prefix.symbols.take(index) << shift
        at += prefix.sizes.take(index)
    value[spot[lit]] = pixel
    if cache:
        rest = (~is_literal).nonzero()[0]
        slot[spot[rest]] = symbol[rest] - GREEN - LENGTHS


def traced(value: np.ndarray, slot: np.ndarray, copies: list[tuple[int, int, int]], cache: int, image: np.ndarray | None = None) -> np.ndarray:
    """Pixels where copies and cached colours have the values of the literals that they repeat; ``image`` parts the pixels of
    several images, which share no cache.

    A cached colour repeats the last pixel before it that fell into its slot; a copied pixel falls into the slot of
    the one it copies.
    """
    if not copies and not (slot >= 0).any():
        return value.astype(np.uint32)
    source = np.arange(len(value))
    for pos, run, back in copies:
        if back >= run:
            source[pos : pos + run] = source[pos - back : pos - back + run]
        else:
            source[pos : pos + run] = np.resize(source[pos - back : pos], run)
    if cache:
        asks = slot >= 0
        falls = np.where(asks, slot, (value * CACHE_FACTOR & 0xFFFFFFFF) >> (32 - cache))[source]
        order = np.argsort(falls.astype(np.uint16), kind="stable")
        before = np.full(len(value), -1)
        same = falls[order[1:]] == falls[order[:-1]]
        if image is not None:
            same &= image[order[1:]] == image[order[:-1]]
        same = same.nonzero()[0]
        before[order[same + 1]] = order[same]
        first = asks & (before < 0)  # an empty slot is 0
        source = np.where(asks & ~first, before, source)
    while (up := source.take(source)).tobytes() != source.tobytes():
        source = up
    return value.take(source).astype(np.uint32)


def _read_symbols(bits: Bits, groups: list[tuple], width: int, total: int, cache: int, block: int, of_block: list[int] | None, tally: dict[str, int] | None) -> list[int]:
    out: list[int] = []
    put, words, at = out.append, bits.words, bits.at
    kept, fresh, shift, across = [0] * (1 << cache), 0, 32 - cache, -(-width >> block)
    green, green_m, red, red_m, blue, blue_m, alpha, alpha_m, distance, distance_m = groups[0]
    pos = references = cached = copied = 0
    while pos < total:
        if of_block is not None:
            green, green_m, red, red_m, blue, blue_m, alpha, alpha_m, distance, distance_m = groups[of_block[(pos // width >> block) * across + (pos % width >> block)]]
        word = words[at >> 3] >> (at & 7)
        g = green[word & green_m]
        n = g & 15
        if g < OTHER:
            word >>= n
            r = red[word & red_m]
            k = r & 15
            word >>= k
            n += k
            b = blue[word & blue_m]
            n += b & 15
            at += n
            a = alpha[(words[at >> 3] >> (at & 7)) & alpha_m]
            at += a & 15
            put((a | r | g | b) >> 4)
            pos += 1
            continue
        at += n
        s = (g ^ OTHER) >> 4
        if s >= GREEN + LENGTHS:
            for colour in out[fresh:]:
                kept[(colour * CACHE_FACTOR & 0xFFFFFFFF) >> shift] = colour
            fresh = pos
            put(kept[s - GREEN - LENGTHS])
            pos += 1
            cached += 1
            continue
        bits.at = at
        run = extra_of(s - GREEN, bits)
        d = distance[words[bits.at >> 3] >> (bits.at & 7) & distance_m]
        bits.at += d & 15
        back = plane_of(extra_of(d >> 4, bits), width)
        at = bits.at
        if back > pos or pos + run > total:
            raise ValueError("a back-reference leaves the image")
        if back >= run:
            out += out[pos - back : pos - back + run]
        else:
            out += (out[pos - back :] * -(-run // back))[:run]
        pos += run
        references += 1
        copied += run
    bits.at = at
    if tally is not None:
        for name, count in (("literals", total - copied - cached), ("references", references), ("cached", cached)):
            tally[name] = tally.get(name, 0) + count
    return out


def opened(data: bytes) -> tuple[Bits, int, int, list[tuple], int]:
    """(reader at the main image, width, height, transforms, stored width) of a lossless WebP file or bare VP8L stream."""
    if data[:4] == b"RIFF":
        if data[8:12] != b"WEBP":
            raise ValueError("not a WebP file")
        at, body = 12, None
        while at + 8 <= len(data) and body is None:
            size = int.from_bytes(data[at + 4 : at + 8], "little")
            body = data[at + 8 : at + 8 + size] if data[at : at + 4] == b"VP8L" else None
            at += 8 + size + (size & 1)
        if body is None:
            raise ValueError("no lossless image in the file")
        data = body
    bits = Bits(data)
    if bits.read(8) != SIGNATURE:
        raise ValueError("wrong signature")
    width, height = bits.read(14) + 1, bits.read(14) + 1
    bits.read(1)
    if bits.read(3):
        raise ValueError("unknown version")
    steps, stored = [], width
    while bits.read(1):
        kind = bits.read(2)
        if kind in (0, 1):
            block = bits.read(3) + 2
            steps.append((kind, stored, block, read_pixels(bits, -(-stored >> block), -(-height >> block), False)))
        elif kind == 2:
            steps.append((kind, stored, 0, None))
        else:
            colours = bits.read(8) + 1
            table = read_pixels(bits, colours, 1, False)
            table = joined(*[c.cumsum() & 255 for c in channels(table)])
            steps.append((kind, stored, pack_bits(colours), table))
            stored = -(-stored >> steps[-1][2])
    return bits, width, height, steps, stored


def decode(data: bytes, tally: dict[str, int] | None = None) -> np.ndarray:
    """Pixels (height, width, 4) as A, R, G, B bytes of a lossless WebP file or bare VP8L stream."""
    bits, width, height, steps, stored = opened(data)
    return undone(read_pixels(bits, stored, height, True, tally), width, height, steps, tally)


def undone(argb: np.ndarray, width: int, height: int, steps: list[tuple], tally: dict[str, int] | None = None) -> np.ndarray:
    """Pixels as A, R, G, B bytes of the stored words, with the transforms taken back."""
    for kind, before, block, extra in reversed(steps):
        if tally is not None:
            name = ("predictor", "cross_colour", "green", "palette")[kind]
            tally[name] = tally.get(name, 0) + 1
        if kind == 0:
            argb = predict(argb, before, block, extra, True)
        elif kind == 1:
            argb = cross(argb, before, block, extra, True)
        elif kind == 2:
            a, r, g, b = channels(argb)
            argb = joined(a, r + g, g, b + g)
        else:
            index = channels(argb)[2].reshape(height, -1)
            n = 8 >> block
            split = (index[:, :, None] >> (n * np.arange(1 << block))) & ((1 << n) - 1)
            index = split.reshape(height, -1)[:, :before].ravel()
            argb = np.where(index < len(extra), extra[np.minimum(index, len(extra) - 1)], np.uint32(0))
    return argb.astype(">u4").view(np.uint8).reshape(height, width, 4)
