"""Lossless WebP of many small images at once: what one image does by many short array calls is done by a few long ones.

The results are those of ``webp_write`` and ``webp_read`` for each image and do not depend on what else is in a batch. Transforms
are estimated and earlier equal pixels found for all images together; on reading, all images' symbols are followed side by
side, one symbol of each at a time.
"""

from __future__ import annotations

import numpy as np

from .webp_planes import GREEN, LENGTHS
from .webp_read import Bits, Prefix, extra_of, opened, plane_of, group_of, read_pixels, traced, undone
from .webp_write import WIDE_BLOCK, _N_LOG_N, cost_of, cross_left, factors_of, filed, headed, palette_cost, write_many

#: Symbols that are followed between two looks at back-references and ended images, and the fewest images worth it.
STEPS, LEAST_IMAGES = 32, 48
#: How much longer than the ``LEAST_IMAGES``-th longest an image may be to be read beside the others.
LONGER = 1.2
#: Bits that one look gives for sure.
LOOK = 56


def _group_costs(images: np.ndarray, n: int, samples: np.ndarray) -> np.ndarray:
    """Bits of every image's 8-bit samples under one code."""
    counts = np.bincount(images * 256 + samples, minlength=256 * n).reshape(n, 256)
    total = counts.sum(axis=1)
    return _N_LOG_N[total] - _N_LOG_N[counts].sum(axis=1)


def _palette_costs(words: np.ndarray, images: np.ndarray, n: int) -> tuple[list[int], list[float]]:
    """(colours, ``palette_cost`` where it is one index a byte) of every image."""
    if n > 256 or len(words) > 1 << 24:
        raise ValueError("too many images at once")
    keys = images.astype(np.uint64) << np.uint64(56) | words.astype(np.uint64) << np.uint64(24) | np.arange(len(words), dtype=np.uint64)
    keys.sort()
    order, ordered = (keys & np.uint64((1 << 24) - 1)).astype(np.int64), keys >> np.uint64(24)
    new = np.concatenate([[True], ordered[1:] != ordered[:-1]])
    table, of_colour = (ordered[new] & np.uint64(0xFFFFFFFF)).astype("<u4"), (ordered[new] >> np.uint64(32)).astype(np.int64)
    colours = np.bincount(of_colour, minlength=n)
    index = np.empty(len(words), dtype=np.int64)
    index[order] = new.cumsum() - 1
    index -= (colours.cumsum() - colours)[images]
    samples = table.view(np.uint8).reshape(-1, 4)
    steps = samples.copy()
    steps[1:] -= samples[:-1] * (of_colour[1:] == of_colour[:-1])[:, None]
    fits = colours[images] <= 256
    costs = 200 + _group_costs(np.repeat(of_colour, 4), n, steps.ravel()) + _group_costs(images[fits], n, index[fits])
    return colours.tolist(), costs.tolist()


def stored(images: list[np.ndarray], cache: int) -> list[bytes]:
    """Files of (height, width, 4) images of one width: each with the transform that costs least, references and a cache."""
    width, n = images[0].shape[1], len(images)
    sizes = np.array([x.shape[0] * width for x in images])
    ends = sizes.cumsum()
    starts = ends - sizes
    p = np.concatenate([x.reshape(-1, 4) for x in images])
    of_pixel = np.repeat(np.arange(n), sizes)
    of_sample = np.repeat(of_pixel, 4)
    flat = p.ravel()
    alike = p.copy()
    alike[:, 1::2] -= p[:, 2:3]
    costs = [_group_costs(of_sample, n, flat), _group_costs(of_sample, n, alike.ravel())]
    for step in (4, 4 * width):  # as in ``chosen``, the first pixels are left out
        inside = np.ones(len(flat), dtype=bool)
        for k in range(step):
            inside[np.minimum(4 * starts + k, 4 * ends - 1)] = False
        at = inside.nonzero()[0]
        costs.append(np.where(4 * sizes > step, 100 + 8 * step + _group_costs(of_sample[at], n, flat[at] - flat[at - step]), np.inf))
    different, palette = _palette_costs(p.view("<u4").ravel(), of_pixel, n)
    signed = p[:, 1:].T.copy().view(np.int8).astype(np.int64)
    sums = np.add.reduceat(signed, starts, axis=1)
    products = np.add.reduceat(signed[[1, 0, 2, 0, 2]] * signed[[1, 1, 1, 0, 2]], starts, axis=1)
    out = []
    for i, (one, costs_of) in enumerate(zip(images, np.stack(costs, axis=1).tolist())):
        own = slice(starts[i], ends[i])
        options = [{}, {"green": True}, {"predictor": 1}, {"predictor": 2}]
        factors = factors_of(int(sizes[i]), sums[:, i].tolist(), products[:, i].tolist())
        if any(factors):
            options.append({"cross_colour": factors})
            costs_of.append(100 + cost_of(cross_left(p[own], width, factors)))
        if different[i] <= 256:  # packed indices, of up to 16 colours, are not estimated together
            options.append({"palette": True})
            costs_of.append(palette[i] if different[i] > 16 else palette_cost(p[own], width))
        out.append(headed(one, **options[costs_of.index(min(costs_of))], block=WIDE_BLOCK))
    return [filed(body) for body in write_many(out, cache)]


def read_many(files: list[bytes]) -> list[np.ndarray]:
    """``webp_read.decode`` of every file; those with one code group and the same cache size are read side by side."""
    out: list[np.ndarray | None] = [None] * len(files)
    beside: dict[int, list[tuple]] = {}
    for i, data in enumerate(files):
        bits, width, height, steps, stored_width = opened(data)
        at = bits.at
        cache, group = group_of(bits)
        if group is None or group[0].depth == 0 or sum(p.depth for p in group[:4]) > LOOK:
            bits.at = at
            out[i] = undone(read_pixels(bits, stored_width, height, True), width, height, steps)
        else:
            beside.setdefault(cache, []).append((i, bits, group, width, height, steps, stored_width))
    for cache, found in beside.items():
        # the few that are much longer than most would be followed almost alone
        found.sort(key=lambda x: x[4] * x[6], reverse=True)
        limit = LONGER * found[min(len(found), LEAST_IMAGES) - 1][4] * found[min(len(found), LEAST_IMAGES) - 1][6]
        alone = len(found) if len(found) < LEAST_IMAGES else sum(x[4] * x[6] > limit for x in found)
        pixels = [read_pixels(bits, stored_width, height, True, codes=(cache, group)) for _, bits, group, _, height, _, stored_width in found[:alone]]
        if alone < len(found):
            pixels += _side_by_side([(bits, group, stored_width, stored_width * height) for _, bits, group, _, height, _, stored_width in found[alone:]], cache)
        for (i, _, _, width, height, steps, _), argb in zip(found, pixels):
            out[i] = undone(argb, width, height, steps)
    return out


class _Tables:
    """The codes of many images as one table each of symbols and of lengths; where a code begins, and its mask, by image."""

    def __init__(self):
        self.known: dict[int, int] = {}
        self.symbols, self.sizes, self.at = [], [], 0

    def add(self, prefix: Prefix, sizes: np.ndarray | None = None) -> tuple[int, int]:
        if id(prefix) not in self.known:
            self.known[id(prefix)] = self.at
            self.symbols.append(prefix.symbols)
            self.sizes.append(prefix.sizes if sizes is None else sizes)
            self.at += len(prefix.symbols)
        return self.known[id(prefix)], (1 << prefix.depth) - 1


#: Marks literals among the lengths of green codes; a reference has length 0 and no mark, so its image stops there.
_LITERAL = -1 << 8


def _green_sizes(green: Prefix) -> np.ndarray:
    refers = (green.symbols >= GREEN) & (green.symbols < GREEN + LENGTHS)
    return np.where(green.symbols < GREEN, _LITERAL | green.sizes, np.where(refers, 0, green.sizes))


def _side_by_side(images: list[tuple[Bits, list[Prefix], int, int]], cache: int) -> list[np.ndarray]:
    """ARGB words of images (reader at the first symbol, codes, width, pixels) with one code group and cache size."""
    n = len(images)
    greens, others = _Tables(), _Tables()
    codes = [[greens.add(g[0], _green_sizes(g[0])), *[others.add(x) for x in g[1:4]]] for _, g, _, _ in images]
    base = np.array([[c[0] for c in own] for own in codes]).T.copy()
    mask = np.array([[c[1] for c in own] for own in codes]).T.copy()
    green_sizes, other_sizes = np.concatenate(greens.sizes), np.concatenate(others.sizes)
    first = np.cumsum([0] + [len(bits.data) + 16 for bits, _, _, _ in images])
    data = b"".join(bits.data + bytes(16) for bits, _, _, _ in images)
    words = np.ndarray(len(data) - 8, dtype="<i8", buffer=data, strides=(1,)).astype(np.int64)
    here = 8 * first[:-1] + np.array([bits.at for bits, _, _, _ in images])
    ends = 8 * first[:-1] + np.array([bits.end for bits, _, _, _ in images])
    total = np.array([x[3] for x in images])
    offset = total.cumsum() - total
    left, lanes = total.copy(), np.arange(n)
    copies: list[tuple[int, int, int]] = []
    told: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    trace = np.empty((STEPS + 1, n), dtype=np.int64)
    row, most = np.arange(STEPS)[:, None], 8 * len(words) - 1
    while len(lanes):
        (g0, r0, b0, a0), (gm, rm, bm, am) = base[:, lanes], mask[:, lanes]
        path = trace[:, : len(lanes)]
        path[0] = at = here[lanes]
        for step in range(1, STEPS + 1):
            w = words.take(at >> 3)
            w >>= at & 7
            g = green_sizes.take((w & gm) + g0)
            n_g = g & 15
            w >>= n_g
            r = other_sizes.take((w & rm) + r0)
            w >>= r
            b = other_sizes.take((w & bm) + b0)
            w >>= b
            r += b
            r += other_sizes.take((w & am) + a0)
            g >>= 8
            r &= g
            r += n_g
            r += at
            at = np.minimum(r, most, out=path[step])  # an ended image goes on over what follows
        moved = (path[1:] != path[:-1]).sum(axis=0)
        taken = np.minimum(moved, left[lanes])
        inside = row < taken
        spot = (offset + total - left)[lanes] + row
        told.append((path[:-1][inside], np.broadcast_to(lanes, inside.shape)[inside], spot[inside]))
        here[lanes] = path[taken, np.arange(len(lanes))]
        left[lanes] -= taken
        if (here > ends).any():
            raise ValueError("the bit stream is too short")
        for lane in lanes[(left[lanes] > 0) & (moved < STEPS)].tolist():  # at a reference
            bits, group, width, _ = images[lane]
            bits.at = int(here[lane] - 8 * first[lane])
            look = bits.words[bits.at >> 3] >> (bits.at & 7) & int(mask[0, lane])
            bits.at += int(group[0].sizes[look])
            run = extra_of(int(group[0].symbols[look]) - GREEN, bits)
            look = bits.words[bits.at >> 3] >> (bits.at & 7) & (1 << group[4].depth) - 1
            bits.at += int(group[4].sizes[look])
            back = plane_of(extra_of(int(group[4].symbols[look]), bits), width)
            pos = int(total[lane] - left[lane])
            if back > pos or run > left[lane]:
                raise ValueError("a back-reference leaves the image")
            if bits.at > bits.end:
                raise ValueError("the bit stream is too short")
            copies.append((int(offset[lane]) + pos, run, back))
            left[lane] -= run
            here[lane] = 8 * first[lane] + bits.at
        lanes = lanes[left[lanes] > 0]
    at, lane, spot = (np.concatenate(x) for x in zip(*told))
    value, slot = np.zeros(int(total.sum()), dtype=np.int64), np.full(int(total.sum()), -1, dtype=np.int64)
    w = words.take(at >> 3) >> (at & 7)
    index = (w & mask[0].take(lane)) + base[0].take(lane)
    symbol = np.concatenate(greens.symbols).take(index)
    cached = symbol >= GREEN
    slot[spot[cached]] = symbol[cached] - GREEN - LENGTHS
    plain = (~cached).nonzero()[0]
    w, lane, pixel, symbols = w[plain] >> (green_sizes.take(index[plain]) & 15), lane[plain], symbol[plain] << 8, np.concatenate(others.symbols)
    for k, shift in ((1, 16), (2, 0), (3, 24)):
        index = (w & mask[k].take(lane)) + base[k].take(lane)
        pixel |= symbols.take(index) << shift
        w >>= other_sizes.take(index)
    value[spot[plain]] = pixel
    argb = traced(value, slot, copies, cache, np.repeat(np.arange(n), total))
    return np.split(argb, offset[1:])
