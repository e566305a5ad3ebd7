"""Continuous sharing: buffer a person's day, release it once it is closed; or point by point against a budget."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..config import Cfg
from ..plans.batch import Blocks
from ..plans.kernel import Kernel
from ..plans.knowledge import Knowledge

_OUT = "traj_id string, pos int, poi_id string, t int"
#: Visits of open days, and how many groups of people keep them.
_OPEN = ["traj_id", "day", "t", "poi"]
_STATE = "traj_id array<string>, day array<string>, t array<int>, poi array<string>"
BUCKETS = 1024


def stamped(points: DataFrame, delay: str = "2 hours") -> DataFrame:
    """Points with an event-time watermark (columns user_id, ts, poi_id); NTZ times are cast first."""
    return points.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)


def deduplicated(points: DataFrame) -> DataFrame:
    """Repeats of a point within the watermark are dropped."""
    return points.dropDuplicatesWithinWatermark(["user_id", "poi_id", "ts"])


def visitors(points: DataFrame, width: str = "1 hour", slide: str | None = None) -> DataFrame:
    """Visits per place and tumbling (or sliding) window."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return points.groupBy(w.alias("w"), "poi_id").agg(F.count(F.lit(1)).alias("visits")).select(F.col("w.start").alias("start"), "poi_id", "visits")


def sessions(points: DataFrame, quiet: str = "6 hours") -> DataFrame:
    """Visits of a person until a quiet gap."""
    return points.groupBy(F.session_window("ts", quiet).alias("s"), "user_id").agg(F.count(F.lit(1)).alias("visits")).select(F.col("s.start").alias("start"), F.col("s.end").alias("end"), "user_id", "visits")


def with_places(points: DataFrame, poi: DataFrame) -> DataFrame:
    """Stream-static join with the public catalog."""
    return points.join(F.broadcast(poi.select("poi_id", "l1")), "poi_id")


def share_days(points: DataFrame, k: Knowledge, cfg: Cfg, method: str = "hier", min_len: int = 3, max_len: int = 8, buckets: int = BUCKETS) -> DataFrame:
    """Released trajectories of closed user-days, by the same keyed draws as the batch run.

    A day closes when the watermark passes its end. Days outside the length range or with an infeasible visit give nothing.
    The state is kept for ``buckets`` of people: a call then serves many days, whose closed ones are released block by
    block. Without a seed in ``cfg`` this call draws a secret one; give one that is kept with the checkpoint where a query
    is started again, so that a repeated batch repeats its draws.
    """
    cfg, held = cfg.secret(), []
    shared = points.sparkSession.sparkContext.broadcast(k.shipped())

    def work(key, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        parts = [pd.DataFrame(dict(zip(_OPEN, state.get)))] if state.exists else []
        if not state.hasTimedOut:
            for f in frames:
                slot = ((f["ts"].dt.hour * 60 + f["ts"].dt.minute) // cfg.gt_min).astype(int)
                parts.append(pd.DataFrame({"traj_id": f["person"] + "|" + f["day"], "day": f["day"], "t": slot, "poi": f["poi_id"]}))
        # of a slot's visits the least place counts
        visits = pd.concat(parts).sort_values(_OPEN).drop_duplicates(["traj_id", "t"])
        days, of_day = np.unique(visits["day"].to_numpy(dtype=object), return_inverse=True)
        close = np.array([int(pd.Timestamp(d).value // 1_000_000) + 86_400_000 for d in days], dtype=np.int64)
        now = state.getCurrentWatermarkMs()
        closed = (close < now)[of_day]
        left = visits[~closed]
        if len(left):
            state.update(tuple(left[c].tolist() for c in _OPEN))
            state.setTimeoutTimestamp(max(int(close[close >= now].min()), now + 1))
        elif state.exists:
            state.remove()
        if closed.any():
            if not held:  # one per task
                held.append(Blocks(Kernel(shared.value, cfg)))
            yield from _closed_days(visits[closed], held[0], method, min_len, max_len)

    day = F.date_format("ts", "yyyy-MM-dd")
    keyed = points.select(F.col("user_id").cast("string").alias("person"), "ts", "poi_id", day.alias("day"))
    dealt = keyed.withColumn("bucket", F.pmod(F.xxhash64("person"), F.lit(buckets)))
    return dealt.groupBy("bucket").applyInPandasWithState(work, _OUT, _STATE, "append", GroupStateTimeout.EventTimeTimeout)


def _closed_days(visits: pd.DataFrame, blocks: Blocks, method: str, min_len: int, max_len: int) -> Iterator[pd.DataFrame]:
    """The releases of whole days (rows in order of day and slot)."""
    kernel, ids = blocks.kernel, visits["traj_id"].to_numpy(dtype=object)
    place = np.array([kernel.number.get(p, -1) for p in visits["poi"]], dtype=np.int64)
    t = visits["t"].to_numpy(dtype=np.int64)
    start = np.concatenate([[0], (ids[1:] != ids[:-1]).nonzero()[0] + 1])
    size = np.diff(np.concatenate([start, [len(ids)]]))
    for length in range(min_len, max_len + 1):
        first = start[size == length]
        at = first[:, None] + np.arange(length)
        fits = [min(p) >= 0 and kernel.feasible(p, s) for p, s in zip(place[at].tolist(), t[at].tolist())]
        at = at[np.array(fits, dtype=bool)]
        for block in blocks.run(method, ids[at[:, 0]].tolist(), place[at], t[at], None) if len(at) else ():
            names = np.array(blocks.k.poi_ids, dtype=object)[block.poi.ravel()]
            yield pd.DataFrame({"traj_id": np.repeat(block.ids, length), "pos": np.tile(np.arange(1, length + 1), len(block.ids)), "poi_id": names, "t": block.t.ravel()})


def share_points(points: DataFrame, k: Knowledge, cfg: Cfg, expected: int = 8) -> DataFrame:
    """Point-by-point release: each spends eps / expected from the person's day; once spent, nothing more is released.

    Points of a batch go in order of their time. The seed is as in ``share_days``.
    """
    cfg, held = cfg.secret(), []
    shared = points.sparkSession.sparkContext.broadcast(k.shipped())

    def work(key, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        used = state.get[0] if state.exists else 0
        if not held:  # one per task
            held.append(Kernel(shared.value, cfg.but(eps=2 * cfg.eps / expected)))
        kernel, rows = held[0], []
        for ts, poi in sorted((ts, poi) for f in frames for ts, poi in zip(f["ts"], f["poi_id"])):
            if used >= expected or poi not in kernel.number:
                continue
            used += 1
            r = kernel.run("indep_free", f"{key[0]}|{key[1]}|{used}", [poi], [(ts.hour * 60 + ts.minute) // cfg.gt_min], cfg.eps / expected)
            rows.append((f"{key[0]}|{key[1]}", used, r["poi"][0], r["t"][0]))
        state.update((used,))
        yield pd.DataFrame(rows, columns=["traj_id", "pos", "poi_id", "t"])

    keyed = points.select("user_id", "ts", "poi_id", F.date_format("ts", "yyyy-MM-dd").alias("day"))
    return keyed.groupBy("user_id", "day").applyInPandasWithState(work, _OUT, "used int", "append", GroupStateTimeout.NoTimeout)
