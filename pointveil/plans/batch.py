"""The kernels over many trajectories of one length and budget at once, with the rows that ``Kernel.run`` gives one by one.

Weights, sums and paths are arrays with one row per trajectory; draws are keyed as in the kernel. Whatever a block cannot
settle for certain (a number on the edge between two nodes, a path that the cheapest nodes do not prove the best) goes
through the kernel's own functions for that trajectory. Stage seconds are a block's, in equal shares.
"""

from __future__ import annotations

import time
from collections import OrderedDict
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np

from ..functions.rng import draw
from ..operators.budget import split_value
from ..operators.expmech import sensitivity
from .kernel import FLOAT_BYTES, Chain, Kernel, viterbi, windows_of

#: Trajectories times nodes of a block, and the nodes of a position that are looked at before all of them.
BLOCK_CELLS, CHEAPEST = 1 << 17, (16, 48, 128)
#: Numbers closer than this share of a row's weight to the edge between two nodes are settled by the kernel.
EDGE = 1e-9


@dataclass
class Block:
    """Released trajectories of one length: one row each; z has (first, last, nodes of every trajectory) by window."""

    ids: list[str]
    poi: np.ndarray
    t: np.ndarray
    smoothed: np.ndarray
    attempts: np.ndarray
    connected: np.ndarray
    z: list[tuple[int, int, np.ndarray]]
    stages: list[float]


def picks(weights: np.ndarray, u: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(index by weight, whether it is too near an edge to be sure) of every row."""
    c = weights.cumsum(axis=1)
    whole = c[:, -1]
    target = u * whole
    at = np.minimum((c <= target[:, None]).sum(axis=1), c.shape[1] - 1)
    rows = np.arange(len(c))
    below = np.where(at > 0, c[rows, at - 1], -np.inf)
    return at, ~(np.minimum(target - below, c[rows, at] - target) > EDGE * whole)


def _scaled(weights: np.ndarray) -> np.ndarray:
    weights /= np.maximum(weights.max(axis=1, keepdims=True), 1e-300)
    return weights


def _us(seed: str, ids: list[str], a: int, b: int, n: int) -> np.ndarray:
    return np.array([[draw(seed, i, a, b, j) for j in range(n)] for i in ids])


def best_paths(cost: np.ndarray, linked: Callable[[int, np.ndarray, np.ndarray], np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """(paths, whether each is the kernel's) of least summed cost (trajectories x positions x nodes, changed in place).

    ``linked(i, rows, before, after)`` tells which nodes before may precede position ``i``'s. A path through the
    cheapest nodes of each position is the best of all where any other node alone would already cost more.
    """
    n, length, nodes = cost.shape
    path, sure = np.zeros((n, length), dtype=np.int64), np.zeros(n, dtype=bool)
    if length > 2:
        cost[:, 1:-1] *= 2.0
    low = cost.min(axis=2)
    for k in CHEAPEST:
        rows = (~sure).nonzero()[0]
        if not len(rows) or k >= nodes and k != CHEAPEST[0]:
            break
        k = min(k, nodes)
        part = cost if len(rows) == n else cost[rows]
        near = np.sort(np.argpartition(part, k - 1, axis=2)[:, :, :k], axis=2)
        each = np.take_along_axis(part, near, axis=2)
        total, back = each[:, 0], []
        for i in range(1, length):
            ways = np.where(linked(i, rows, near[:, i - 1, None, :], near[:, i, :, None]), total[:, None, :], np.inf)
            arg = ways.argmin(axis=2)
            total = np.take_along_axis(ways, arg[:, :, None], axis=2)[:, :, 0] + each[:, i]
            back.append(arg)
        last = total.argmin(axis=1)
        all_ = np.arange(len(rows))
        least = total[all_, last]
        spare = least - low[rows].sum(axis=1) + 1e-9 * (1 + np.abs(least))
        fits = np.isfinite(least)
        needed = (part <= (low[rows] + np.where(fits, spare, np.inf)[:, None])[:, :, None]).sum(axis=2).max(axis=1)
        done = fits & (needed <= k)
        for i in range(length - 1, -1, -1):
            path[rows, i] = near[all_, i, last]
            if i:
                last = back[i - 1][all_, last]
        sure[rows[done]] = True
    return path, sure


class Blocks:
    """All methods over one kernel, block by block."""

    def __init__(self, kernel: Kernel):
        self.kernel, self.k, self.cfg = kernel, kernel.k, kernel.cfg
        self.tables: OrderedDict = OrderedDict()
        self.laws: OrderedDict = OrderedDict()
        self.rows: tuple = (None, None, None)
        self.before = None if self.k.A is None else np.ascontiguousarray(self.k.A.T)
        # slots after which a place is reached: no place within less than one
        self.reach = np.array([-1.0] + [kernel.reach_km(g) for g in range(1, self.cfg.slots + 1)])
        self.all_reach = float(kernel.km9.max())

    def feasible(self, pois: np.ndarray, t: np.ndarray) -> np.ndarray:
        """``Kernel.feasible`` of every row."""
        gap = np.diff(t, axis=1)
        near = self.kernel.km9[pois[:, :-1], pois[:, 1:]] <= self.reach[np.maximum(gap, 0)]
        return self.k.open_slots[pois, t].all(axis=1) & ((gap > 0) & near).all(axis=1)

    def run(self, method: str, ids: list[str], pois: np.ndarray, t: np.ndarray, eps: float | None) -> Iterator[Block]:
        """Blocks of trajectories (rows of place numbers and slots) of one length."""
        nodes = len(self.k.D) if method == "hier" else len(self.k.poi_ids)
        step = max(1, min(512, BLOCK_CELLS // nodes))
        for at in range(0, len(ids), step):
            one = getattr(self, method, None) or (lambda *given: self._singly(method, *given))
            yield one(ids[at : at + step], pois[at : at + step], t[at : at + step], eps)

    def _singly(self, method, ids, pois, t, eps) -> Block:
        names = self.k.poi_ids
        rows = [self.kernel.run(method, i, [names[x] for x in p], s, eps) for i, p, s in zip(ids, pois.tolist(), t.tolist())]
        number = self.kernel.number
        return Block(
            ids, np.array([[number[x] for x in r["poi"]] for r in rows]), np.array([r["t"] for r in rows]), *[np.array([r[c] for r in rows]) for c in ("smoothed", "attempts", "connected")],
            [(*w[:2], np.array([r["z"][i][2] for r in rows])) for i, w in enumerate(rows[0]["z"])], np.mean([r["stages"] for r in rows], axis=0).tolist(),
        )

    def _law(self, d: np.ndarray, nodes: np.ndarray, eps: float, delta: float) -> np.ndarray:
        """Weights of all nodes by the distances ``d`` from each of ``nodes``; of few nodes, the last tables are kept."""
        if 8 * d.size > FLOAT_BYTES // 8:
            return np.exp(-eps * d[nodes] / (2 * delta))
        key = id(d), eps, delta
        if key not in self.laws:
            self.laws[key] = np.exp(-eps * d / (2 * delta))
            if len(self.laws) > 12:
                self.laws.popitem(last=False)
        self.laws.move_to_end(key)
        return self.laws[key].take(nodes, axis=0)

    # -- region n-grams

    def _weights(self, nodes: np.ndarray, eps: float, delta: float) -> np.ndarray:
        return self._law(self.k.D, nodes, eps, delta)

    def _led(self, nodes: np.ndarray, eps: float, delta: float) -> np.ndarray:
        """What a window's last region gives to the regions before it, by row; for all regions at once where they are few,
        else when a region is first met, and the last table is kept."""
        adjacency, r = self.kernel.chain.a, len(self.k.D)
        key = eps, delta
        if 8 * r * r > FLOAT_BYTES // 8:
            if self.rows[0] != key:
                self.rows = key, np.empty((r, r)), np.zeros(r, dtype=bool)
            _, table, known = self.rows
            some = np.unique(nodes[~known[nodes]])
            if len(some):
                table[some], known[some] = _scaled(self._weights(some, eps, delta)) @ adjacency.T, True
            return table[nodes]
        if key not in self.tables:
            self.tables[key] = _scaled(self._weights(np.arange(r), eps, delta)) @ adjacency.T
            if len(self.tables) > 12:
                self.tables.popitem(last=False)
        self.tables.move_to_end(key)
        return self.tables[key][nodes]

    def release(self, ids: list[str], regions: np.ndarray, eps_total: float | None) -> list[tuple[int, int, np.ndarray]]:
        """``Kernel.release`` of every row."""
        cfg, length, chain = self.cfg, regions.shape[1], self.kernel.chain
        spans = windows_of(length, cfg.n, cfg.overlap)
        eps = split_value(length, cfg, "hier", eps_total) if cfg.overlap else (cfg.eps if eps_total is None else eps_total) / len(spans)
        edges, out = self.k.A, []
        for a, b in spans:
            m = b - a + 1
            delta, us, gram = sensitivity(m, self.k.diameter, cfg.delta_mode), _us(cfg.seed, ids, a, b, m), regions[:, a : b + 1]
            messages = [_scaled(self._weights(gram[:, -1], eps, delta))]
            for i in range(m - 2, -1, -1):
                led = self._led(gram[:, -1], eps, delta) if i == m - 2 else messages[0] @ chain.a.T
                messages.insert(0, _scaled(self._weights(gram[:, i], eps, delta) * led))
            path = np.empty((len(ids), m), dtype=np.int64)
            path[:, 0], unsure = picks(messages[0], us[:, 0])
            for i in range(1, m):
                path[:, i], near = picks(messages[i] * edges[path[:, i - 1]], us[:, i])
                unsure |= near
            for row in unsure.nonzero()[0]:
                found = chain.sample(tuple(gram[row].tolist()), eps, delta, us[row].tolist())
                if found is None:
                    raise ValueError("the region graph has no path of the window's length")
                path[row] = found
            out.append((a, b, path))
        return out

    def _errors(self, z: list[tuple[int, int, np.ndarray]], length: int, to_node: np.ndarray) -> np.ndarray:
        """Summed distances of every node to the released ones, by trajectory and position."""
        out, seen = None, [False] * length
        for a, _, grams in z:
            if out is None:
                out = np.empty((len(grams), length, len(to_node)))
            for i in range(grams.shape[1]):
                if seen[a + i]:
                    out[:, a + i] += to_node[grams[:, i]]
                else:
                    out[:, a + i], seen[a + i] = to_node[grams[:, i]], True
        return out

    def region_paths(self, z: list[tuple[int, int, np.ndarray]], length: int) -> tuple[np.ndarray, np.ndarray]:
        """``Kernel.region_path`` of every row."""
        box, edges = self.k.box, self.before
        cost = self._errors(z, length, self.kernel.to_region)
        if self.cfg.mbr:
            voted = box[np.concatenate([grams for _, _, grams in z], axis=1)]
            south, north, west, east = voted[:, :, 0].min(axis=1), voted[:, :, 1].max(axis=1), voted[:, :, 2].min(axis=1), voted[:, :, 3].max(axis=1)
            inside = (box[:, 0] <= north[:, None]) & (box[:, 1] >= south[:, None]) & (box[:, 2] <= east[:, None]) & (box[:, 3] >= west[:, None])
            cost[np.broadcast_to(~inside[:, None, :], cost.shape)] = np.inf
        path, sure = best_paths(cost, lambda i, rows, before, after: edges[after, before])
        connected = np.ones(len(path), dtype=bool)
        for row in (~sure).nonzero()[0]:
            path[row], connected[row] = self.kernel.region_path([(a, b, grams[row].tolist()) for a, b, grams in z], length)
        return path, connected

    def hier(self, ids, pois, t, eps) -> Block:
        clock = [time.perf_counter()]
        regions = self.k.encode[pois, t * self.cfg.gt_min // 60]
        if regions.min() < 0:
            raise ValueError("a visit lies outside its place's opening hours")
        z = self.release(ids, regions, eps)
        clock.append(time.perf_counter())
        path, connected = self.region_paths(z, pois.shape[1])
        clock.append(time.perf_counter())
        found = self.kernel.fills(ids, path)
        clock.append(time.perf_counter())
        return Block(ids, *found, connected, z, (np.diff(clock) / len(ids)).tolist())

    # -- places without regions

    def _times(self, ids: list[str], t: np.ndarray, eps: float) -> np.ndarray:
        """Every slot drawn by itself."""
        delta = sensitivity(1, float(self.kernel.slot_d.max()), self.cfg.delta_mode)
        law = np.exp(-eps * self.kernel.slot_d / (2 * delta)).cumsum(axis=1)
        u = np.array([[draw(self.cfg.seed, one, i, i, "time") for i in range(t.shape[1])] for one in ids])
        c = law[t]
        return np.minimum((c <= (u * c[:, :, -1])[:, :, None]).sum(axis=2), self.cfg.slots - 1)

    def _rising(self, t: np.ndarray) -> np.ndarray:
        out = np.sort(t, axis=1)
        for i in range(1, out.shape[1]):
            out[:, i] = np.maximum(out[:, i], out[:, i - 1] + 1)
        over = out[:, -1] >= self.cfg.slots
        out[over, -1] = self.cfg.slots - 1
        for i in range(out.shape[1] - 2, -1, -1):
            out[over, i] = np.minimum(out[over, i], out[over, i + 1] - 1)
        return out

    def flat(self, ids, pois, t, eps, method: str = "flat") -> Block:
        clock = [time.perf_counter()]
        cfg, kernel, length, km = self.cfg, self.kernel, pois.shape[1], self.kernel.km9
        each = split_value(length, cfg, method, eps)
        slots = self._rising(self._times(ids, t, each))
        d, diameter = kernel.place[method]
        gaps = np.diff(slots, axis=1)
        limit = self.reach[np.maximum(gaps, 0)]
        z = []
        for a, b in windows_of(length, cfg.n):
            m = b - a + 1
            delta, us, gram = sensitivity(m, diameter, cfg.delta_mode), _us(cfg.seed, ids, a, b, m), pois[:, a : b + 1]
            messages = [_scaled(self._law(d, gram[:, -1], each, delta))]
            for i in range(m - 2, -1, -1):
                messages.insert(0, _scaled(self._law(d, gram[:, i], each, delta) * self._reached(messages[0], gaps[:, a + i])))
            path = np.empty((len(ids), m), dtype=np.int64)
            path[:, 0], unsure = picks(messages[0], us[:, 0])
            for i in range(1, m):
                path[:, i], near = picks(messages[i] * (km[path[:, i - 1]] <= limit[:, a + i - 1, None]), us[:, i])
                unsure |= near
            for row in unsure.nonzero()[0]:
                edges = [kernel.floats_at(int(g)) for g in gaps[row, a:b]]
                path[row] = Chain(d, edges).sample(tuple(gram[row].tolist()), each, delta, us[row].tolist())
            z.append((a, b, path))
        clock.append(time.perf_counter())
        path, sure = best_paths(self._errors(z, length, d), lambda i, rows, before, after: km[before, after] <= limit[rows, i - 1, None, None])
        if not sure.all():
            error = self._errors([(a, b, grams[~sure]) for a, b, grams in z], length, d)
            for row, one in zip((~sure).nonzero()[0], error):
                path[row] = viterbi(one, [kernel.edges_at(int(g)) for g in gaps[row]])[0]
        clock += [time.perf_counter()] * 2
        n = len(ids)
        return Block(ids, path, slots, np.zeros(n, dtype=bool), np.zeros(n, dtype=np.int64), np.ones(n, dtype=bool), z, (np.diff(clock) / n).tolist())

    def _reached(self, after: np.ndarray, gap: np.ndarray) -> np.ndarray:
        """Summed weights of the places within reach of each place, by row; a gap that reaches all has one sum."""
        out = np.empty_like(after)
        keys = np.where(gap < 1, 0, np.minimum(gap, self.kernel.most_gap))
        for key in np.unique(keys).tolist():
            rows = (keys == key).nonzero()[0]
            if key and self.kernel.reach_km(key) >= self.all_reach:
                out[rows] = after[rows].sum(axis=1, keepdims=True)
            else:
                out[rows] = after[rows] @ self.kernel.floats_at(key).T
        return out

    def geo_only(self, ids, pois, t, eps) -> Block:
        return self.flat(ids, pois, t, eps, "geo_only")

    def indep_free(self, ids, pois, t, eps) -> Block:
        clock = [time.perf_counter()]
        cfg, k, n, length = self.cfg, self.k, *pois.shape
        each = split_value(length, cfg, "indep_free", eps)
        d, diameter = self.kernel.place["flat"]
        delta = sensitivity(1, diameter, cfg.delta_mode)
        out = np.empty_like(pois)
        for i in range(length):
            u = np.array([draw(cfg.seed, one, i, i, "place") for one in ids])
            out[:, i] = picks(self._law(d, pois[:, i], each, delta), u)[0]
        drawn = self._times(ids, t, each)
        clock += [time.perf_counter()] * 2
        slots = self._rising(drawn)
        free = not np.isfinite(cfg.speed_kmh) or cfg.theta == "inf"
        need = np.ones((n, length - 1), dtype=np.int64) if free else np.maximum(1, np.ceil(np.round(k.km[out[:, :-1], out[:, 1:]], 6) / cfg.speed_kmh * 60 / cfg.gt_min)).astype(np.int64)
        fixed = slots.copy()
        for i in range(1, length):
            fixed[:, i] = np.maximum(fixed[:, i], fixed[:, i - 1] + need[:, i - 1])
        over = fixed[:, -1] >= cfg.slots
        fixed[over, -1] = cfg.slots - 1
        for i in range(length - 2, -1, -1):
            fixed[over, i] = np.minimum(fixed[over, i], fixed[over, i + 1] - need[over, i])
        fits = fixed[:, 0] >= 0
        smoothed = ~fits | (fixed != drawn).any(axis=1)
        clock.append(time.perf_counter())
        return Block(ids, out, np.where(fits[:, None], fixed, slots), smoothed, np.zeros(n, dtype=np.int64), fits, [], (np.diff(clock) / n).tolist())

    def indep_reach(self, ids, pois, t, eps) -> Block:
        clock = [time.perf_counter()]
        cfg, kernel, n, length = self.cfg, self.kernel, *pois.shape
        each = split_value(length, cfg, "indep_reach", eps)
        d, diameter = kernel.place["flat"]
        delta, delta_t = sensitivity(1, diameter, cfg.delta_mode), sensitivity(1, float(kernel.slot_d.max()), cfg.delta_mode)
        out, slots, room = np.empty_like(pois), np.empty_like(t), np.arange(cfg.slots)
        law = np.exp(-each * kernel.slot_d / (2 * delta_t))
        for i in range(length):
            free = room <= cfg.slots - (length - i)
            if i:
                free = free & (room > slots[:, i - 1, None])
            slots[:, i] = picks(law[t[:, i]] * free, np.array([draw(cfg.seed, one, i, i, "time") for one in ids]))[0]
            weight = self._law(d, pois[:, i], each, delta)
            if i:
                weight *= kernel.km9[out[:, i - 1]] <= self.reach[slots[:, i] - slots[:, i - 1], None]
            out[:, i] = picks(weight, np.array([draw(cfg.seed, one, i, i, "place") for one in ids]))[0]
        clock += [time.perf_counter()] * 3
        return Block(ids, out, slots, np.zeros(n, dtype=bool), np.zeros(n, dtype=np.int64), np.ones(n, dtype=bool), [], (np.diff(clock) / n).tolist())
