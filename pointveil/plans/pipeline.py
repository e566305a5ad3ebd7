"""One call from trajectories to a released set: a single narrow stage around the kernels."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import Cfg
from ..operators.perturb import packed
from .batch import Block, Blocks
from .kernel import METHODS, Kernel
from .knowledge import Knowledge

_FIELDS = (
    "traj_id string, poi array<string>, t array<int>, smoothed boolean, attempts int, connected boolean, "
    "z array<struct<a:int,b:int,gram:array<long>>>, perturb_s double, path_s double, other_s double, eps double"
)


@dataclass
class RunResult:
    """rows: one per trajectory with everything; the views below are projections of it."""

    rows: DataFrame

    @property
    def released(self) -> DataFrame:
        points = self.rows.select("traj_id", "smoothed", "attempts", F.posexplode(F.arrays_zip("poi", "t")).alias("i", "e"))
        return points.select("traj_id", (F.col("i") + 1).cast("int").alias("pos"), F.col("e.poi").alias("poi_id"), F.col("e.t").alias("t"), "smoothed", "attempts")

    @property
    def z(self) -> DataFrame:
        return self.rows.select("traj_id", F.explode("z").alias("w")).select("traj_id", (F.col("w.a") + 1).alias("a"), (F.col("w.b") + 1).alias("b"), F.col("w.gram").alias("gram"))

    @property
    def timings(self) -> DataFrame:
        return self.rows.agg(F.avg("perturb_s").alias("perturb"), F.avg("path_s").alias("rebuild"), F.avg("other_s").alias("other"), F.avg(F.col("perturb_s") + F.col("path_s") + F.col("other_s")).alias("total"))

    @property
    def ledger(self) -> DataFrame:
        return self.rows.select("traj_id", F.col("eps").alias("total"))


#: Tasks of the private stage for each core: its tables are small, its work is not, so sizes say nothing of time.
TASKS_PER_CORE = 4
_LAST: dict[tuple, Blocks] = {}


def blocks_of(key: tuple, shared, cfg: Cfg) -> Blocks:
    """The kernel of a release, made once in a Python worker; only the last one is held."""
    if key not in _LAST:
        _LAST.clear()
        _LAST[key] = Blocks(Kernel(shared.value, cfg))
    return _LAST[key]


def _lists(values: pa.Array, sizes: np.ndarray) -> pa.ListArray:
    return pa.ListArray.from_arrays(pa.array(np.concatenate([[0], sizes.cumsum()]), pa.int32()), values)


def _record(block: Block, names: pa.Array, eps: float) -> pa.RecordBatch:
    """The rows of a block."""
    n, length = block.poi.shape
    spans = np.array([(a, b) for a, b, _ in block.z], dtype=np.int32).reshape(-1, 2)
    grams = np.concatenate([g for _, _, g in block.z], axis=1).ravel() if block.z else np.zeros(0, dtype=np.int64)
    windows = np.tile(spans, (n, 1))
    gram = _lists(pa.array(grams, pa.int64()), (windows[:, 1] - windows[:, 0] + 1).astype(np.int64))
    z = pa.StructArray.from_arrays([pa.array(windows[:, 0], pa.int32()), pa.array(windows[:, 1], pa.int32()), gram], ["a", "b", "gram"])
    full = np.full(n, length)
    columns = [
        pa.array(block.ids, pa.string()), _lists(names.take(pa.array(block.poi.ravel())), full), _lists(pa.array(block.t.ravel(), pa.int32()), full),
        pa.array(block.smoothed, pa.bool_()), pa.array(block.attempts, pa.int32()), pa.array(block.connected, pa.bool_()), _lists(z, np.full(n, len(spans))),
        *[pa.array(np.full(n, s), pa.float64()) for s in block.stages], pa.array(np.full(n, eps), pa.float64()),
    ]
    return pa.RecordBatch.from_arrays(columns, ["traj_id", "poi", "t", "smoothed", "attempts", "connected", "z", "perturb_s", "path_s", "other_s", "eps"])


def dealt(rows: DataFrame, releases: int = 1) -> DataFrame:
    """Rows by trajectory in a given number of tasks, which adaptive execution does not join into one; fewer for each of many releases."""
    cores = rows.sparkSession.sparkContext.defaultParallelism
    return rows.repartition(max(cores, TASKS_PER_CORE * cores // releases), "traj_id")


def _groups(batch: pa.RecordBatch, names: pa.Array) -> Iterator[tuple[list[str], np.ndarray, np.ndarray, float | None]]:
    """(ids, place numbers, slots, budget) of the packed trajectories of one length and budget."""
    ids, seq = batch.column("traj_id").to_pylist(), batch.column("seq")
    start = seq.offsets.to_numpy()
    points = seq.values
    place = pc.index_in(points.field("poi_id"), value_set=names)
    if place.null_count:
        raise ValueError("a visit's place is not in the catalog")
    place, slot = place.to_numpy().astype(np.int64), points.field("t").to_numpy().astype(np.int64)
    own = batch.column("eps").to_pylist() if "eps" in batch.schema.names else [None] * len(ids)
    groups: dict[tuple, list[int]] = {}
    for row, (size, eps) in enumerate(zip(np.diff(start).tolist(), own)):
        groups.setdefault((size, None if eps is None or eps != eps else float(eps)), []).append(row)
    for (size, eps), rows in groups.items():
        at = start[rows][:, None] + np.arange(size)
        yield [ids[r] for r in rows], place[at], slot[at], eps


def run(method: str, traj: DataFrame, k: Knowledge, cfg: Cfg, budgets: DataFrame | None = None) -> RunResult:
    """Perturb and rebuild every trajectory by ``method``; ``budgets`` (traj_id, eps) gives personal budgets.

    One shuffle packs each trajectory; what follows is row-local in one mapInArrow over the broadcast public arrays,
    block by block of trajectories of one length.
    Without a seed in ``cfg`` every call draws a secret one, so two calls are two releases; the result of one call repeats
    its draws wherever a task is run again. Persist it.
    """
    if method not in METHODS:
        raise ValueError(f"unknown method {method}")
    cfg = cfg.secret()
    shared = traj.sparkSession.sparkContext.broadcast(k.shipped())
    key = uuid.uuid4().hex, cfg
    rows = packed(dealt(traj), "poi_id", "t")  # packing needs no further shuffle
    rows = rows.join(budgets, "traj_id", "left") if budgets is not None else rows.withColumn("eps", F.lit(None).cast("double"))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        blocks = blocks_of(key, shared, cfg)
        names = pa.array(blocks.k.poi_ids, pa.string())
        for batch in batches:
            if batch.num_rows:
                for ids, place, slot, eps in _groups(batch, names):
                    for block in blocks.run(method, ids, place, slot, eps):
                        yield _record(block, names, cfg.eps if eps is None else eps)

    return RunResult(rows.mapInArrow(work, _FIELDS))


def valid_packs(packs: DataFrame, k: Knowledge, cfg: Cfg) -> DataFrame:
    """Packed trajectories whose legs are all reachable and whose visits are all open, as ``reach.valid_only`` has them;
    ``k`` needs places only."""
    shared, key = packs.sparkSession.sparkContext.broadcast(k.shipped()), (uuid.uuid4().hex, cfg)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        blocks = blocks_of(key, shared, cfg)
        names = pa.array(blocks.k.poi_ids, pa.string())
        for batch in batches:
            if batch.num_rows:
                number = pa.RecordBatch.from_arrays([pa.array([str(i) for i in range(batch.num_rows)]), batch.column("seq")], ["traj_id", "seq"])
                kept = np.zeros(batch.num_rows, dtype=bool)
                for rows, place, slot, _ in _groups(number, names):
                    kept[np.array(rows, dtype=np.int64)] = blocks.feasible(place, slot)
                yield batch.filter(pa.array(kept))

    return packs.mapInArrow(work, packs.schema)


Told = Callable[[Kernel, Block, np.ndarray, np.ndarray], dict[str, list | np.ndarray]]


def measured(packs: DataFrame, releases: list[tuple[str, Knowledge, Cfg]], tell: Told, fields: str) -> DataFrame:
    """What ``tell`` says of each block of every release, for experiments that compare releases with the truth.

    packs: packed trajectories. A release (method, knowledge, settings) is drawn as in ``run`` and compared where it is drawn,
    so nothing is joined again; ``tell(kernel, block, places, slots)`` gives columns ``fields``, best already added up, and
    ``setting`` is the release's number. All releases are one job; a task has one of them.
    """
    context, out, shipped = packs.sparkSession.sparkContext, [], {}
    rows = dealt(packs, len(releases))
    columns = [f.split()[0] for f in fields.split(", ")]
    for setting, (method, k, cfg) in enumerate(releases):
        if method not in METHODS:
            raise ValueError(f"unknown method {method}")
        if id(k) not in shipped:
            shipped[id(k)] = context.broadcast(k.shipped())
        out.append(rows.mapInArrow(_teller(setting, method, shipped[id(k)], cfg.secret(), tell, columns), f"setting int, {fields}"))
    return reduce(DataFrame.unionByName, out)


def _teller(setting: int, method: str, shared, cfg: Cfg, tell: Told, columns: list[str]):
    key = uuid.uuid4().hex, cfg

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        blocks = blocks_of(key, shared, cfg)
        names = pa.array(blocks.k.poi_ids, pa.string())
        for batch in batches:
            if batch.num_rows:
                for ids, place, slot, eps in _groups(batch, names):
                    at = 0
                    for block in blocks.run(method, ids, place, slot, eps):
                        own = slice(at, at := at + len(block.ids))
                        told = [pa.array(x) for x in map(tell(blocks.kernel, block, place[own], slot[own]).get, columns)]
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(told[0]), setting), pa.int32()), *told], ["setting", *columns])

    return work
