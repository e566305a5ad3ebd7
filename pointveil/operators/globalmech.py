"""The whole-trajectory mechanism: literal over an enumerated output set (toys), and exactly by a chain."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import expmech


def enumerate_outputs(points: DataFrame, length: int, ok, most: int = 1_000_000) -> DataFrame:
    """All trajectories of a toy (cand string, points array): points (node, t) joined while ``ok(prev, next)`` holds.

    Refuses when points ** length could pass ``most``.
    """
    n = points.count()
    if n**length > most:
        raise ValueError(f"{n} ** {length} trajectories exceed {most}; use the chain form")
    item = F.struct("node", "t")
    out = points.select(F.array(item).alias("points"))
    for _ in range(length - 1):
        nxt = points.select(item.alias("nx"))
        out = out.join(F.broadcast(nxt), ok(F.element_at("points", -1), F.col("nx"))).select(F.concat("points", F.array("nx")).alias("points"))
    return out.withColumn("cand", F.array_join(F.transform("points", lambda p: F.concat_ws("@", p["node"].cast("string"), p["t"].cast("string"))), ">"))


def distances(inputs: DataFrame, outputs: DataFrame, each) -> DataFrame:
    """(input, cand, dist): positionwise sum against every output; inputs has (input, points)."""
    j = inputs.select("input", F.col("points").alias("x")).join(F.broadcast(outputs.select("cand", F.col("points").alias("y"))))
    total = F.aggregate(F.zip_with("x", "y", each), F.lit(0.0), lambda s, v: s + v)
    return j.select("input", "cand", total.alias("dist"))


def run(inputs: DataFrame, outputs: DataFrame, each, eps: float, delta: float, seed: str, form: str = "em", rate: float = 0.1) -> DataFrame:
    """(input, chosen) by the full draw, the subsampled one or permute-and-flip."""
    pairs = distances(inputs, outputs, each)
    if form == "subsample":
        return expmech.draw_subsample(pairs, ["input"], eps, delta, seed, rate)
    if form == "flip":
        return expmech.draw_flip(pairs, ["input"], eps, delta, seed)
    return expmech.draw_gumbel(pairs, ["input"], eps, delta, seed)


def chain_draw(kernel, traj: str, pois: list[int], t: list[int], eps: float | None = None) -> tuple[list[int], list[int]]:
    """One draw over all feasible (place, slot) sequences: backward sums over states, later slots first.

    The distance of a state is the norm of kilometres, hours and category; its weight sums over the positions.
    """
    from ..functions.rng import draw
    from ..plans.kernel import pick

    k, cfg = kernel.k, kernel.cfg
    eps = cfg.eps if eps is None else eps
    slots, places = cfg.slots, len(k.poi_ids)
    far = float(np.sqrt(k.km.max() ** 2 + 144 + k.cat.max() ** 2))
    delta = expmech.sensitivity(len(pois), far, cfg.delta_mode)
    weight = []
    for p, s in zip(pois, t):
        d = np.sqrt((k.km[p] ** 2 + k.cat[p] ** 2)[:, None] + kernel.slot_d[s][None, :] ** 2)
        weight.append(np.exp(-eps * d / (2 * delta)) * k.open_slots)
    most = int(np.ceil(k.km.max() * 60 / (cfg.gt_min * max(cfg.speed_kmh, 1e-9)))) + 1
    after = [weight[-1]]
    for w in reversed(weight[:-1]):
        nxt, total = after[-1], np.zeros((places, slots))
        suffix = np.cumsum(nxt[:, ::-1], axis=1)[:, ::-1]
        for gap in range(1, min(most, slots)):
            total[:, : slots - gap] += kernel.edges_at(gap).astype(np.float64) @ nxt[:, gap:]
        if most < slots:  # past the diameter every later slot reaches every place
            total[:, : slots - most] += (kernel.edges_at(most).astype(np.float64) @ suffix)[:, most:]
        w = w * total
        after.append(w / max(w.max(), 1e-300))
    after.reverse()
    flat = pick(after[0].ravel(), draw(cfg.seed, traj, "all", 0))
    path = [divmod(flat, slots)]
    for i in range(1, len(pois)):
        p, s = path[-1]
        ok = np.zeros((places, slots))
        for gap in range(1, slots - s):
            ok[:, s + gap] = kernel.edges_at(gap)[p]
        flat = pick((after[i] * ok).ravel(), draw(cfg.seed, traj, "all", i))
        path.append(divmod(flat, slots))
    return [p for p, _ in path], [s for _, s in path]


def tail_bound(length: int, diameter: float, eps: float, n_out: float, zeta: float) -> float:
    """Loss bound of the whole-trajectory draw."""
    return expmech.tail_bound(eps, length * diameter, n_out, zeta)
