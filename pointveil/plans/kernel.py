"""Per-trajectory kernels of all methods in numpy: draws, rebuild, fill, smoothing.

A kernel sees one trajectory and public arrays only. Its randomness is keyed by (seed, trajectory, window), so a
retried task repeats its draws.
"""

from __future__ import annotations

import time
from collections import OrderedDict

import numpy as np

from ..config import Cfg
from ..functions.rng import draw
from ..operators.budget import split_value
from ..operators.expmech import sensitivity
from .knowledge import Knowledge

#: Bytes of place edges held as numbers.
FLOAT_BYTES = 64 << 20
#: Graphs of so few nodes are looked through as a whole.
SMALL = 256
#: Odd step of the fill's counters, its attempts that are drawn together, and those made before the rest is counted.
STEP = 0x9E3779B97F4A7C15
FILL_TRIES = 1 << 16
FIRST_TRIES = (1, 32)
#: Numbers that counting completions holds at once.
COUNT_CELLS = 1 << 19
METHODS = ("hier", "flat", "geo_only", "indep_reach", "indep_free", "global")


def pick(weights: np.ndarray, u: float) -> int:
    """Index drawn by weight."""
    c = weights.cumsum()
    return int(min(np.searchsorted(c, u * c[-1], side="right"), len(c) - 1))


class Chain:
    """Draws from the exponential mechanism over all paths of a graph, without listing them.

    A path's distance is the sum of its positions' distances, so its weight is a product along the path: backward
    sums give the weight of all continuations, and nodes are drawn one after the other. On one fixed graph the sums of
    the ends that many windows share are kept.
    """

    def __init__(self, distance: np.ndarray, adjacency: list[np.ndarray] | np.ndarray, keep: int = 4096):
        self.d, self.a, self.keep = distance, adjacency, keep
        self.memo: OrderedDict = OrderedDict()

    def _edge(self, i: int) -> np.ndarray:
        return self.a[i] if isinstance(self.a, list) else self.a

    def _weight(self, node: int, eps: float, delta: float, led: np.ndarray | None) -> np.ndarray:
        w = np.exp(-eps * self.d[node] / (2 * delta))
        if led is not None:
            w = w * led
        return w / max(w.max(), 1e-300)

    def _end(self, gram: tuple[int, ...], eps: float, delta: float) -> tuple[np.ndarray, np.ndarray]:
        """The first position's message of an end of a window, and what it gives to a node before it."""
        key = (gram, round(eps, 12), round(delta, 12))
        if key in self.memo:
            self.memo.move_to_end(key)
            return self.memo[key]
        after = self._weight(gram[0], eps, delta, self._end(gram[1:], eps, delta)[1] if len(gram) > 1 else None)
        found = self.memo[key] = after, self.a @ after
        if len(self.memo) > self.keep:
            self.memo.popitem(last=False)
        return found

    def messages(self, gram: tuple[int, ...], eps: float, delta: float) -> list[np.ndarray]:
        """For every position, node weight times the weight of all continuations (scaled)."""
        if not isinstance(self.a, list):
            ends = [self._end(gram[i:], eps, delta) for i in range(1, len(gram))]
            return [self._weight(gram[0], eps, delta, ends[0][1] if ends else None), *[m for m, _ in ends]]
        out, after = [], None
        for i in range(len(gram) - 1, -1, -1):
            after = self._weight(gram[i], eps, delta, None if after is None else self._edge(i) @ after)
            out.append(after)
        return out[::-1]

    def sample(self, gram: tuple[int, ...], eps: float, delta: float, us: list[float]) -> list[int] | None:
        """One path, or nothing if the graph has no path of that length."""
        m = self.messages(gram, eps, delta)
        if m[0].sum() <= 0:
            return None
        path = [pick(m[0], us[0])]
        for i in range(1, len(gram)):
            path.append(pick(m[i] * self._edge(i - 1)[path[-1]], us[i]))
        return path


def windows_of(length: int, n: int, overlap: bool = True) -> list[tuple[int, int]]:
    """0-based (first, last) of main windows, then prefixes and suffixes."""
    m = min(n, length)
    if not overlap:
        return [(a, min(a + m, length) - 1) for a in range(0, length, m)]
    out = [(a, a + m - 1) for a in range(length - m + 1)]
    for k in range(1, m):
        out += [(0, k - 1), (length - k, length - 1)]
    return out


def cheapest(cost: np.ndarray, edge: np.ndarray, nodes: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """For every node the predecessor of least cost and that cost (ties: the least id; none: 0 and infinity).

    Predecessors are tried from the cheapest on, so a node is settled by the first that has an edge to it. ``nodes``
    are the rows and columns of ``edge`` that the positions of ``cost`` stand for.
    """
    if len(cost) <= SMALL:
        total = np.where(edge if nodes is None else edge[np.ix_(nodes, nodes)], cost[:, None], np.inf)
        best = total.argmin(axis=0)
        return best, total[best, np.arange(len(cost))]
    order = np.argsort(cost, kind="stable")
    order = order[: int(np.isfinite(cost).sum())]
    best, least = np.zeros(len(cost), dtype=np.int64), np.full(len(cost), np.inf)
    todo, at, step = np.arange(len(cost)), 0, 24
    while len(todo) and at < len(order):
        rows = order[at : at + step]
        if nodes is not None:
            part = edge[np.ix_(nodes[rows], nodes[todo])]
        else:
            part = edge[rows] if len(todo) == len(cost) else edge[np.ix_(rows, todo)]
        first = part.argmax(axis=0)
        hit = part[first, np.arange(len(todo))]
        got, by = todo[hit], rows[first[hit]]
        best[got], least[got] = by, cost[by]
        todo, at, step = todo[~hit], at + step, step * 6
    return best, least


def viterbi(node: np.ndarray, edges: list[np.ndarray] | np.ndarray, nodes: np.ndarray | None = None) -> tuple[list[int], float] | None:
    """Path of least bigram error; inner positions are in two bigrams and count twice. Ties: least ids.

    ``nodes``: the rows and columns of the edges that columns of ``node`` stand for, if not all in order.
    """
    length = len(node)
    if length == 1:
        best = int(node[0].argmin())
        return [best], float(node[0][best])
    weight = np.full(length, 2.0)
    weight[[0, -1]] = 1.0
    cost, back = node[0] * weight[0], []
    for i in range(1, length):
        arg, before = cheapest(cost, edges[i - 1] if isinstance(edges, list) else edges, nodes)
        cost = before + node[i] * weight[i]
        back.append(arg)
    last = int(cost.argmin())
    if not np.isfinite(cost[last]):
        return None
    path = [last]
    for arg in reversed(back):
        path.append(int(arg[path[-1]]))
    return path[::-1], float(cost[last])


def smooth(k: Knowledge, pois: list[int], t: list[int], cfg: Cfg) -> list[int] | None:
    """Times moved forward until every leg fits, then back from the end of the day; nothing if the day is too short."""
    need = [0] + [max(1, int(np.ceil(np.round(k.km[a, b], 6) / cfg.speed_kmh * 60 / cfg.gt_min))) if np.isfinite(cfg.speed_kmh) and cfg.theta != "inf" else 1 for a, b in zip(pois, pois[1:])]
    out = list(t)
    for i in range(1, len(out)):
        out[i] = max(out[i], out[i - 1] + need[i])
    if out[-1] >= cfg.slots:
        out[-1] = cfg.slots - 1
        for i in range(len(out) - 2, -1, -1):
            out[i] = min(out[i], out[i + 1] - need[i + 1])
    return out if out[0] >= 0 else None


def _flat(lists: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(all values, where each list begins, its length)."""
    size = np.array([len(x) for x in lists], dtype=np.int64)
    return np.concatenate(lists) if lists else np.zeros(0, dtype=np.int64), size.cumsum() - size, size


def _mixed(x: np.ndarray) -> np.ndarray:
    """Uniform 64-bit numbers from keys plus counters times ``STEP``."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _below(x: np.ndarray, n: np.ndarray) -> np.ndarray:
    """The same below ``n`` (under 2**32)."""
    return ((_mixed(x) >> np.uint64(32)) * n.astype(np.uint64) >> np.uint64(32)).astype(np.int64)


def _unit(x: np.ndarray) -> np.ndarray:
    """The same in (0, 1)."""
    return ((_mixed(x) >> np.uint64(12)).astype(np.float64) + 0.5) / (1 << 52)


class Kernel:
    """All methods over one knowledge bundle."""

    def __init__(self, k: Knowledge, cfg: Cfg):
        self.k, self.cfg = k, cfg
        self.number = {p: i for i, p in enumerate(k.poi_ids)}
        self.chain = Chain(k.D, k.A.astype(np.float64)) if k.D is not None else None
        self.gap_edges: OrderedDict = OrderedDict()
        self.gap_floats: OrderedDict = OrderedDict()
        self.km9 = k.km.round(9)
        self.most_gap = int(np.ceil(k.km.max() * 60 / (cfg.gt_min * max(cfg.speed_kmh, 1e-9)))) + 1
        self.to_region = None if k.D is None else np.ascontiguousarray(k.D.T)
        place = {"flat": np.sqrt(k.km**2 + k.cat**2), "geo_only": k.km}
        self.place = {m: (d, float(d.max()) or 1.0) for m, d in place.items()}
        self.slot_h = np.abs(np.arange(cfg.slots)[:, None] - np.arange(cfg.slots)) * cfg.gt_min / 60
        self.slot_d = np.minimum(self.slot_h, 12.0)
        self.members_flat, self.members_at, self.members_n = _flat(k.region_members)
        self.slots_flat, self.slots_at, self.slots_n = _flat(k.region_slots)
        # least slots between two places; more than a day where no gap is enough
        gaps = np.arange(1, cfg.slots + 1)
        limit = gaps * cfg.gt_min * cfg.speed_kmh / 60 if cfg.theta == "gap" else np.full(len(gaps), self.reach_km(1))
        self.need = np.searchsorted(limit, self.km9) + 1

    # -- shared pieces

    def reach_km(self, gap: int) -> float:
        c = self.cfg
        return {"inf": np.inf, "fixed": c.theta_fixed_km, "slot": c.gt_min * c.speed_kmh / 60}.get(c.theta, gap * c.gt_min * c.speed_kmh / 60)

    def _gap_key(self, gap: int) -> int:
        return 0 if gap < 1 else min(gap, self.most_gap)

    def edges_at(self, gap: int) -> np.ndarray:
        """Reachable place pairs within a gap; the same for all gaps past the city's diameter."""
        key = self._gap_key(gap)
        if key not in self.gap_edges:
            self.gap_edges[key] = self.km9 <= self.reach_km(gap) if gap >= 1 else np.zeros_like(self.k.km, dtype=bool)
            if len(self.gap_edges) > 64:
                self.gap_edges.popitem(last=False)
        return self.gap_edges[key]

    def floats_at(self, gap: int) -> np.ndarray:
        """The same as numbers; as many gaps are kept as ``FLOAT_BYTES`` hold."""
        key = self._gap_key(gap)
        if key not in self.gap_floats:
            self.gap_floats[key] = self.edges_at(gap).astype(np.float64)
            if len(self.gap_floats) > max(1, FLOAT_BYTES // self.gap_floats[key].nbytes):
                self.gap_floats.popitem(last=False)
        else:
            self.gap_floats.move_to_end(key)
        return self.gap_floats[key]

    def feasible(self, pois: list[int], t: list[int], hours: bool = True) -> bool:
        if hours and not all(self.k.open_slots[p, s] for p, s in zip(pois, t)):
            return False
        return all(b > a and np.round(self.k.km[p, q], 9) <= self.reach_km(b - a) for p, q, a, b in zip(pois, pois[1:], t, t[1:]))

    def _draw_times(self, traj: str, t: list[int], eps: float) -> list[int]:
        delta = sensitivity(1, float(self.slot_d.max()), self.cfg.delta_mode)
        return [pick(np.exp(-eps * self.slot_d[s] / (2 * delta)), draw(self.cfg.seed, traj, i, i, "time")) for i, s in enumerate(t)]

    def _rising(self, t: list[int]) -> list[int]:
        """Released slots made strictly rising inside the day (uses released values only)."""
        out = sorted(t)
        for i in range(1, len(out)):
            out[i] = max(out[i], out[i - 1] + 1)
        over = out[-1] - (self.cfg.slots - 1)
        if over > 0:
            out[-1] = self.cfg.slots - 1
            for i in range(len(out) - 2, -1, -1):
                out[i] = min(out[i], out[i + 1] - 1)
        return out

    # -- region n-grams

    def encode(self, pois: list[int], t: list[int]) -> list[int]:
        regions = [int(self.k.encode[p, s * self.cfg.gt_min // 60]) for p, s in zip(pois, t)]
        if min(regions) < 0:
            raise ValueError("a visit lies outside its place's opening hours")
        return regions

    def release(self, traj: str, regions: list[int], eps_total: float | None = None) -> list[tuple[int, int, list[int]]]:
        """The released windows z(a, b), 0-based: the only step that sees the true regions."""
        cfg, length = self.cfg, len(regions)
        spans = windows_of(length, cfg.n, cfg.overlap)
        eps = split_value(length, cfg, "hier", eps_total) if cfg.overlap else (cfg.eps if eps_total is None else eps_total) / len(spans)
        out = []
        for a, b in spans:
            m = b - a + 1
            us = [draw(cfg.seed, traj, a, b, i) for i in range(m)]
            path = self.chain.sample(tuple(regions[a : b + 1]), eps, sensitivity(m, self.k.diameter, cfg.delta_mode), us)
            if path is None:
                raise ValueError("the region graph has no path of the window's length")
            out.append((a, b, path))
        return out

    def region_path(self, z: list[tuple[int, int, list[int]]], length: int) -> tuple[list[int], bool]:
        """The continuous region path of least error; (path, connected)."""
        votes = [[] for _ in range(length)]
        for a, _, gram in z:
            for i, r in enumerate(gram):
                votes[a + i].append(r)
        keep = np.arange(len(self.k.D))
        if self.cfg.mbr:
            boxes = self.k.box[np.unique(np.concatenate(votes))]
            south, north, west, east = boxes[:, 0].min(), boxes[:, 1].max(), boxes[:, 2].min(), boxes[:, 3].max()
            b = self.k.box
            keep = np.flatnonzero((b[:, 0] <= north) & (b[:, 1] >= south) & (b[:, 2] <= east) & (b[:, 3] >= west))
        error = np.stack([self.to_region[v].sum(axis=0) for v in votes])
        if len(keep) < len(self.k.D) and (found := viterbi(error[:, keep], self.k.A, keep)) is not None:
            return [int(keep[i]) for i in found[0]], True
        if (found := viterbi(error, self.k.A)) is not None:
            return found[0], True
        return [int(i) for i in error.argmin(axis=1)], False

    def fill(self, traj: str, path: list[int]) -> tuple[list[int], list[int], bool, int]:
        """Places and slots of a region path: (places, slots, smoothed, attempts)."""
        p, t, smoothed, attempts = self.fills([traj], np.array([path]))
        return p[0].tolist(), t[0].tolist(), bool(smoothed[0]), int(attempts[0])

    def fills(self, ids: list[str], paths: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """The same for many paths of one length. Numbers are mixed from a trajectory's key and a counter, so attempts
        of many trajectories are drawn together, and places only where the slots rise."""
        cfg, k, (n, length) = self.cfg, self.k, paths.shape
        keys = [int(draw(cfg.seed, traj, "fill") * 16**13) for traj in ids]
        key = np.array(keys, dtype=np.uint64) * np.uint64(0xD1342543DE82EF95)
        places, slots = np.zeros((n, length), dtype=np.int64), np.zeros((n, length), dtype=np.int64)
        smoothed, attempts, todo = np.zeros(n, dtype=bool), np.zeros(n, dtype=np.int64), np.ones(n, dtype=bool)
        members_n, slots_n = self.members_n[paths], self.slots_n[paths]
        most = np.zeros(n, dtype=np.int64)
        if cfg.fill == "chain":
            for row in range(n):
                found = self._fill_chain([k.region_members[r] for r in paths[row]], [k.region_slots[r] for r in paths[row]], np.random.default_rng(keys[row]))
                if found is not None:
                    (places[row], slots[row]), attempts[row], todo[row] = found, 1, False
        elif cfg.fill == "reject":
            choices = (members_n.astype(np.float64) * slots_n).prod(axis=1)
            most = np.minimum(choices, cfg.gamma).astype(np.int64)

        def drawn(start: np.ndarray, rows: np.ndarray, i: int, flat: np.ndarray, at: np.ndarray, size: np.ndarray, column: int) -> np.ndarray:
            """Members of the lists at position ``i`` by rows and the starts of their tries."""
            return flat[at[paths[:, i]][rows] + _below(start + np.uint64(column * STEP % (1 << 64)), size[:, i][rows])]

        def slot_at(start: np.ndarray, rows: np.ndarray, i: int) -> np.ndarray:
            return drawn(start, rows, i, self.slots_flat, self.slots_at, slots_n, length + i)

        def places_at(start: np.ndarray, rows: np.ndarray) -> np.ndarray:
            return np.stack([drawn(start, rows, i, self.members_flat, self.members_at, members_n, i) for i in range(length)])

        def starts_of(rows: np.ndarray, tries: np.ndarray) -> np.ndarray:
            return key[rows] + (tries * (2 * length)).astype(np.uint64) * np.uint64(STEP)

        # where no attempt can succeed, as slots that cannot rise at all, all count as made
        early = np.full(n, -1)
        for i in range(length):
            early = np.maximum(early + 1, self.slots_flat[self.slots_at[paths[:, i]]])
            late = self.slots_flat[self.slots_at[paths[:, i]] + slots_n[:, i] - 1]
            early = np.where(early > late, cfg.slots, early)
        hopeless = early >= cfg.slots
        tried = 0
        for batch in FIRST_TRIES:
            if not len(rows := (todo & ~hopeless & (most > tried)).nonzero()[0]):
                break
            for part in np.array_split(rows, -(-len(rows) * batch // FILL_TRIES)):
                size = np.minimum(batch, most[part] - tried)
                at, starts = np.repeat(part, size), size.cumsum() - size
                tries = np.arange(len(at)) - np.repeat(starts, size) + tried
                start = starts_of(at, tries)
                t = slot_at(start, at, 0)[None]
                for i in range(1, length):
                    new = slot_at(start, at, i)
                    left = (new > t[-1]).nonzero()[0]
                    at, tries, start, t = at[left], tries[left], start[left], np.concatenate([t[:, left], new[None, left]])
                p = places_at(start, at)
                ok = k.open_slots[p, t].all(axis=0)
                if length > 1:
                    gap = np.diff(t, axis=0)
                    limit = gap * cfg.gt_min * cfg.speed_kmh / 60 if cfg.theta == "gap" else np.full(gap.shape, self.reach_km(1))
                    ok &= (self.km9[p[:-1], p[1:]] <= limit).all(axis=0)
                good = ok.nonzero()[0]
                row, first = np.unique(at[good], return_index=True)
                good = good[first]
                places[row], slots[row], attempts[row], todo[row] = p[:, good].T, t[:, good].T, tries[good] + 1, False
            tried += batch
        # what is left: the number of further tries until one fits, and what that one is, are drawn by their law
        left = (todo & ~hopeless & (most > tried)).nonzero()[0]
        if len(left):
            start, step = starts_of(left, np.full(len(left), 1 << 41)), np.arange(length + 1).astype(np.uint64) * np.uint64(STEP)
            tries, p, t = self._completions(paths[left], _unit(start[:, None] + step))
            fits = tries <= most[left] - tried
            row = left[fits]
            places[row], slots[row], attempts[row], todo[row] = p[fits], t[fits], tries[fits].astype(np.int64) + tried, False
        for row in todo.nonzero()[0]:
            smoothed[row], attempts[row] = True, most[row]
            again = np.full(64, row)
            start = starts_of(again, (1 << 40) + np.arange(64))
            p, t = places_at(start, again).T, np.stack([slot_at(start, again, i) for i in range(length)], axis=1)
            for one, at in zip(p.tolist(), t.tolist()):
                out = smooth(k, one, at, cfg)
                if out is not None:
                    places[row], slots[row] = one, out
                    break
            else:
                # nothing that opens and is reached in time was found: the drawn places at rising slots, told by -1 attempts
                late = np.maximum.accumulate(t[-1] - np.arange(length)) + np.arange(length)
                places[row], slots[row], attempts[row] = p[-1], np.minimum(late, cfg.slots - length + np.arange(length)), -1
        return places, slots, smoothed, attempts

    def _possible(self, path: list[int]) -> bool:
        """Whether any places and slots of a region path are open and reached in time."""
        return bool(np.isfinite(self._completions(np.array([path]), np.full((1, len(path) + 1), 0.5))[0][0]))

    def _completions(self, paths: np.ndarray, us: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(tries until one fits, infinite if none can; places; slots) of region paths of one length, by uniform numbers.

        A try draws members and slots of all regions by chance; the share of tries that fit comes from backward sums over
        (member, slot), and the one that fits is drawn forward, so both have the law of trying.
        """
        n, length = paths.shape
        tries, places, slots = np.empty(n), np.empty((n, length), dtype=np.int64), np.empty((n, length), dtype=np.int64)
        wide = int(self.members_n[paths].max())
        step = max(1, COUNT_CELLS // (wide * max(wide, int(self.need.max()) + 1) * int(self.slots_n[paths].max())))
        for at in range(0, n, step):
            own = slice(at, at + step)
            tries[own], places[own], slots[own] = self._completions_of(paths[own], us[own])
        return tries, places, slots

    def _completions_of(self, paths: np.ndarray, us: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        cfg, k, (n, length) = self.cfg, self.k, paths.shape
        all_ = np.arange(n)
        m, s, fit = [], [], []
        for i in range(length):
            r = paths[:, i]
            column, slot = np.arange(self.members_n[r].max()), np.arange(self.slots_n[r].max())
            inside = (column < self.members_n[r][:, None])[:, :, None] & (slot < self.slots_n[r][:, None])[:, None, :]
            m.append(self.members_flat[self.members_at[r][:, None] + np.minimum(column, self.members_n[r][:, None] - 1)])
            s.append(self.slots_flat[self.slots_at[r][:, None] + np.minimum(slot, self.slots_n[r][:, None] - 1)])
            fit.append(k.open_slots[m[i][:, :, None], s[i][:, None, :]] & inside)
        size = (self.members_n[paths] * self.slots_n[paths]).astype(np.float64)
        share = [fit[-1].astype(np.float64)]
        for i in range(length - 2, -1, -1):
            need = self.need[m[i][:, :, None], m[i + 1][:, None, :]]
            gaps = np.arange(int(need.max()) + 1)
            # the share that is left from each slot of the next region on, by the slots that each gap leads to
            rest = np.concatenate([share[0][:, :, ::-1].cumsum(axis=2)[:, :, ::-1], np.zeros((n, share[0].shape[1], 1))], axis=2)
            first = (s[i + 1][:, :, None] < np.arange(cfg.slots + 1)).sum(axis=1)
            reached = first[all_[:, None, None], np.minimum(s[i][:, None, :] + gaps[:, None], cfg.slots)]
            by_gap = rest[all_[:, None, None, None], np.arange(rest.shape[1])[:, None, None], reached[:, None]]
            row = (all_[:, None] * rest.shape[1] + np.arange(rest.shape[1]))[:, None, :] * len(gaps) + need
            led = by_gap.reshape(-1, s[i].shape[1]).take(row.reshape(n * need.shape[1], -1), axis=0).sum(axis=1)
            share.insert(0, fit[i] * led.reshape(fit[i].shape) / size[:, i + 1, None, None])
        whole = np.minimum(share[0].sum(axis=(1, 2)) / size[:, 0], 1.0)
        with np.errstate(divide="ignore"):
            tries = np.where(whole > 0, np.floor(np.log(us[:, 0]) / np.log1p(-whole)) + 1, np.inf)
        places, slots = np.empty((n, length), dtype=np.int64), np.empty((n, length), dtype=np.int64)
        for i in range(length):
            weight = share[i]
            if i:
                weight = weight * (s[i][:, None, :] >= (slots[:, i - 1, None] + self.need[places[:, i - 1, None], m[i]])[:, :, None])
            c = weight.reshape(n, -1).cumsum(axis=1)
            at = np.minimum((c <= (us[:, i + 1] * c[:, -1])[:, None]).sum(axis=1), c.shape[1] - 1)
            places[:, i], slots[:, i] = m[i][all_, at // s[i].shape[1]], s[i][all_, at % s[i].shape[1]]
        return tries, places, slots

    def _fill_chain(self, members, slots, rng) -> tuple[list[int], list[int]] | None:
        """A uniform feasible completion: counts of completions by a backward pass, then forward draws."""
        cfg, k = self.cfg, self.k
        states = []
        for m, s in zip(members, slots):
            p, t = np.repeat(m, len(s)), np.tile(s, len(m))
            ok = k.open_slots[p, t]
            states.append((p[ok], t[ok]))
        links, after = [], [np.ones(len(states[-1][0]))]
        for (p, t), (q, s) in zip(states[-2::-1], states[:0:-1]):
            gap = s[None, :] - t[:, None]
            limit = gap * cfg.gt_min * cfg.speed_kmh / 60 if cfg.theta == "gap" else np.full(gap.shape, self.reach_km(1))
            link = (gap > 0) & (self.km9[np.ix_(p, q)] <= limit)
            links.append(link)
            w = link @ after[-1]
            after.append(w / max(w.max(), 1e-300))
        links.reverse()
        after.reverse()
        if not len(after[0]) or after[0].sum() <= 0:
            return None
        at = [pick(after[0], rng.random())]
        for link, w in zip(links, after[1:]):
            at.append(pick(w * link[at[-1]], rng.random()))
        return [int(states[i][0][j]) for i, j in enumerate(at)], [int(states[i][1][j]) for i, j in enumerate(at)]

    def hier(self, traj: str, pois: list[int], t: list[int], eps: float | None, clock: dict) -> tuple:
        clock["start"] = time.perf_counter()
        z = self.release(traj, self.encode(pois, t), eps)
        clock["perturb"] = time.perf_counter()
        path, connected = self.region_path(z, len(pois))
        clock["path"] = time.perf_counter()
        out = self.fill(traj, path)
        clock["other"] = time.perf_counter()
        return *out, z, connected

    # -- places without regions

    def flat(self, traj: str, pois: list[int], t: list[int], eps: float | None, clock: dict, method: str = "flat") -> tuple:
        """Times by themselves, then place n-grams on the graph of the released gaps."""
        cfg, length = self.cfg, len(pois)
        clock["start"] = time.perf_counter()
        each = split_value(length, cfg, method, eps)
        slots = self._rising(self._draw_times(traj, t, each))
        d, diameter = self.place[method]
        edges = [self.edges_at(b - a) for a, b in zip(slots, slots[1:])]
        as_float = [self.floats_at(b - a) for a, b in zip(slots, slots[1:])]
        z = []
        for a, b in windows_of(length, cfg.n):
            m = b - a + 1
            us = [draw(cfg.seed, traj, a, b, i) for i in range(m)]
            z.append((a, b, Chain(d, as_float[a:b]).sample(tuple(pois[a : b + 1]), each, sensitivity(m, diameter, cfg.delta_mode), us)))
        clock["perturb"] = time.perf_counter()
        votes = [[] for _ in range(length)]
        for a, _, gram in z:
            for i, p in enumerate(gram):
                votes[a + i].append(p)
        error = np.stack([d[v].sum(axis=0) for v in votes])  # place distances are symmetric
        found = viterbi(error, edges) if length > 1 else viterbi(error, [])
        clock["path"] = clock["other"] = time.perf_counter()
        return found[0], slots, False, 0, z, True

    def geo_only(self, traj, pois, t, eps, clock):
        return self.flat(traj, pois, t, eps, clock, "geo_only")

    def indep_free(self, traj: str, pois: list[int], t: list[int], eps: float | None, clock: dict) -> tuple:
        """Every place and time alone; times are then shifted to fit."""
        cfg = self.cfg
        clock["start"] = time.perf_counter()
        each = split_value(len(pois), cfg, "indep_free", eps)
        d, diameter = self.place["flat"]
        delta = sensitivity(1, diameter, cfg.delta_mode)
        out = [pick(np.exp(-each * d[p] / (2 * delta)), draw(cfg.seed, traj, i, i, "place")) for i, p in enumerate(pois)]
        drawn = self._draw_times(traj, t, each)
        clock["perturb"] = clock["path"] = time.perf_counter()
        slots = self._rising(drawn)
        fixed = smooth(self.k, out, slots, cfg)
        clock["other"] = time.perf_counter()
        return out, fixed or slots, fixed != drawn, 0, [], fixed is not None

    def indep_reach(self, traj: str, pois: list[int], t: list[int], eps: float | None, clock: dict) -> tuple:
        """Place and time one after the other among what is reachable from the point released before."""
        cfg = self.cfg
        clock["start"] = time.perf_counter()
        length = len(pois)
        each = split_value(length, cfg, "indep_reach", eps)
        d, diameter = self.place["flat"]
        delta, delta_t = sensitivity(1, diameter, cfg.delta_mode), sensitivity(1, float(self.slot_d.max()), cfg.delta_mode)
        out, slots = [], []
        for i, (p, s) in enumerate(zip(pois, t)):
            room = np.arange(cfg.slots)
            free = (room > (slots[-1] if slots else -1)) & (room <= cfg.slots - (length - i))
            slot = pick(np.exp(-each * self.slot_d[s] / (2 * delta_t)) * free, draw(cfg.seed, traj, i, i, "time"))
            ok = np.ones(len(d)) if not out else self.edges_at(slot - slots[-1])[out[-1]].astype(float)
            out.append(pick(np.exp(-each * d[p] / (2 * delta)) * ok, draw(cfg.seed, traj, i, i, "place")))
            slots.append(slot)
        clock["perturb"] = clock["path"] = clock["other"] = time.perf_counter()
        return out, slots, False, 0, [], True

    def run(self, method: str, traj: str, pois: list[str], t: list[int], eps: float | None = None) -> dict:
        """One released trajectory with its windows and stage times."""
        clock: dict = {}
        if method == "global":
            from ..operators.globalmech import chain_draw

            clock["start"] = time.perf_counter()
            p, s = chain_draw(self, traj, [self.number[x] for x in pois], t, eps)
            clock["perturb"] = clock["path"] = clock["other"] = time.perf_counter()
            p, s, smoothed, attempts, z, connected = p, s, False, 0, [], True
        else:
            p, s, smoothed, attempts, z, connected = getattr(self, method)(traj, [self.number[x] for x in pois], list(t), eps, clock)
        stages = [clock["perturb"] - clock["start"], clock["path"] - clock["perturb"], clock["other"] - clock["path"]]
        return {"poi": [self.k.poi_ids[i] for i in p], "t": [int(x) for x in s], "smoothed": bool(smoothed), "attempts": int(attempts), "z": z, "connected": connected, "stages": stages}
