"""Generators of test populations: a foot-traffic panel and a campus with planted events."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import Cfg
from ..functions.rng import draw
from ..plans.kernel import Kernel, pick
from ..plans.knowledge import Knowledge
from ..plans.pipeline import TASKS_PER_CORE

_FIELDS = "traj_id string, pos int, poi_id string, t int"
#: Planted crowds: first hour, last hour, share of people below 10,000, people otherwise, category.
EVENTS = ((20, 22, 0.05, 500, "c1"), (14, 16, 0.10, 1000, "c2"), (9, 11, 0.20, 2000, "c0"))


def _generate(people: DataFrame, one) -> DataFrame:
    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            rows = [(str(p), i + 1, poi, int(t)) for p in frame["person"] for i, (poi, t) in enumerate(one(str(p)))]
            yield pd.DataFrame(rows, columns=["traj_id", "pos", "poi_id", "t"])

    # the table of people is small and its work is not: dealt by number, or one task would read and make all
    tasks = TASKS_PER_CORE * people.sparkSession.sparkContext.defaultParallelism
    dealt = people.select(F.col("person").cast("string").alias("person")).repartition(tasks, "person")
    return dealt.mapInPandas(work, _FIELDS)


def _length_and_start(rng: np.random.Generator, cfg: Cfg) -> tuple[int, int]:
    return int(rng.integers(3, 9)), int(rng.integers(6 * 60 // cfg.gt_min, 22 * 60 // cfg.gt_min + 1))


def panel(people: DataFrame, k: Knowledge, by_hour: np.ndarray, dwell_min: np.ndarray, cfg: Cfg) -> DataFrame:
    """One trajectory per person: popularity by hour picks places, dwell and 0-60 travel minutes pass between them.

    by_hour: places x 24 weights; dwell_min: sampled dwell minutes. Ends early if nothing is reachable or the day ends.
    """
    shipped, held, open_ = k.shipped(), [], {}

    def one(person: str):
        if not held:  # one per task
            held.append(Kernel(shipped, cfg))
        kernel = held[0]
        rng = np.random.default_rng(int(draw(cfg.seed, "panel", person) * 16**13))
        length, t = _length_and_start(rng, cfg)
        out: list = []
        while len(out) < length and t < cfg.slots:
            if t not in open_:  # the weights of a slot's places, once per task
                open_[t] = by_hour[:, t * cfg.gt_min // 60] * shipped.open_slots[:, t]
            w = open_[t]
            if out:
                w = w * kernel.edges_at(t - out[-1][1])[out[-1][0]]
            if not w.any():
                break
            out.append((pick(w, rng.random()), t))
            t += max(1, int((dwell_min[rng.integers(len(dwell_min))] + rng.uniform(0, 60)) // cfg.gt_min))
        return [(shipped.poi_ids[p], s) for p, s in out]

    return _generate(people, one)


def event_of(person: int, n_people: int) -> int | None:
    """Which planted crowd a person (0-based number) belongs to."""
    at = 0
    for i, (_, _, share, size, _) in enumerate(EVENTS):
        size = size if n_people >= 10_000 else int(share * n_people)
        if at <= person < at + size:
            return i
        at += size
    return None


def campus(people: DataFrame, k: Knowledge, categories: list[str], n_people: int, cfg: Cfg) -> DataFrame:
    """One trajectory per numbered person: gaps U(g_t, 120) minutes, random category then place, reachable next places."""
    shipped, held = k.shipped(), []
    cats = np.array(categories)

    def one(person: str):
        if not held:  # one per task
            held.append(Kernel(shipped, cfg))
        kernel = held[0]
        rng = np.random.default_rng(int(draw(cfg.seed, "campus", person) * 16**13))
        length, t = _length_and_start(rng, cfg)
        planted = event_of(int(person), n_people)
        fixed = None
        if planted is not None:
            first, last, _, _, cat = EVENTS[planted]
            pool = np.flatnonzero(cats == cat)
            place = int(pool[0]) if planted < 2 else int(pool[rng.integers(min(5, len(pool)))])
            t = int(rng.integers(first * 60 // cfg.gt_min, last * 60 // cfg.gt_min))
            fixed = place
        out: list = []
        while len(out) < length and t < cfg.slots:
            if fixed is not None:
                p, fixed = fixed, None
            else:
                w = shipped.open_slots[:, t].astype(float)
                w = w * (kernel.edges_at(t - out[-1][1])[out[-1][0]] if out else cats == rng.choice(np.unique(cats)))
                if w.sum() <= 0:
                    break
                p = pick(w, rng.random())
            out.append((p, t))
            t += max(1, int(rng.uniform(cfg.gt_min, 120) // cfg.gt_min))
        return [(shipped.poi_ids[p], s) for p, s in out]

    return _generate(people, one)
