"""The public knowledge of one city: places, regions, edges and the arrays kernels need.

Everything here derives from public tables only and costs no budget. Sizes are checked before anything is
broadcast: above ``dense_regions`` places or regions building stops, since one metro's public tables are what a task
holds; larger areas are given metro by metro.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame

from ..config import Cfg
from ..functions.distance import EARTH_KM, TIME_CAP_H, category_value
from ..operators import reach, regions


def haversine_matrix(lat: np.ndarray, lon: np.ndarray) -> np.ndarray:
    """All pairwise great-circle kilometres."""
    a, b = np.radians(lat), np.radians(lon)
    h = np.sin((a[:, None] - a) / 2) ** 2 + np.cos(a[:, None]) * np.cos(a) * np.sin((b[:, None] - b) / 2) ** 2
    return 2 * EARTH_KM * np.arcsin(np.sqrt(np.minimum(1, h)))


def category_matrix(paths: list[str]) -> np.ndarray:
    """Pairwise category distances, taken once per pair of distinct nodes."""
    nodes, back = np.unique(np.array(paths, dtype=object), return_inverse=True)
    small = np.array([[category_value(a, b) for b in nodes] for a in nodes])
    return small[np.ix_(back, back)]


@dataclass
class Knowledge:
    """Arrays over places (P) and regions (R); D and A are region distances and edges, km and cat place distances."""

    poi_ids: list[str]
    lat: np.ndarray
    lon: np.ndarray
    open_slots: np.ndarray  # P x slots
    km: np.ndarray
    cat: np.ndarray
    popularity: np.ndarray
    region_members: list[np.ndarray] = field(default_factory=list)
    region_slots: list[np.ndarray] = field(default_factory=list)
    encode: np.ndarray | None = None  # P x 24 -> region or -1
    D: np.ndarray | None = None
    A: np.ndarray | None = None
    box: np.ndarray | None = None  # R x 4
    diameter: float = 0.0
    regions: pd.DataFrame | None = None
    members: pd.DataFrame | None = None

    def shipped(self) -> "Knowledge":
        """Without the tables of regions and members, to travel to executors."""
        out = Knowledge(**{k: v for k, v in self.__dict__.items() if k not in ("regions", "members")})
        return out


def places(poi: DataFrame, cfg: Cfg) -> Knowledge:
    """Place arrays of a catalog whose size is checked first."""
    most = cfg.dense_regions * 4
    p = poi.select("poi_id", "lat", "lon", "l3", "open_h", "close_h", "popularity").limit(most + 1).toPandas().sort_values("poi_id").reset_index(drop=True)
    if len(p) > most:
        raise ValueError(f"more than {most} places: split the public catalog by tile first")
    hours = np.arange(cfg.slots) * cfg.gt_min // 60
    o, c = p["open_h"].fillna(0).to_numpy()[:, None], p["close_h"].fillna(24).to_numpy()[:, None]
    c = np.where(c < o, c + 24, c)
    open_ = ((hours >= o) & (hours < c)) | ((hours + 24 >= o) & (hours + 24 < c))
    lat, lon = p["lat"].to_numpy(), p["lon"].to_numpy()
    return Knowledge(p["poi_id"].tolist(), lat, lon, open_, haversine_matrix(lat, lon), category_matrix(p["l3"].tolist()), p["popularity"].to_numpy(dtype=np.float64))


def catalogued(poi: DataFrame, cfg: Cfg, cells: DataFrame | None = None) -> tuple[Knowledge, pd.DataFrame]:
    """Places and their open hours before merging; the same for every threshold and order of merging."""
    return places(poi, cfg), regions.assign(poi, cfg, cells, True).toPandas()


def build(poi: DataFrame, cfg: Cfg, cells: DataFrame | None = None, weight: str | None = None, read: tuple[Knowledge, pd.DataFrame] | None = None) -> Knowledge:
    """Places, regions and region edges of a scenario; ``weight`` is a column to hold against kappa instead of the number of places,
    ``read`` what ``catalogued`` gave, if read already.

    The catalog's size is checked, so its open hours are merged on the driver: the ladder has ten steps, each of them jobs otherwise.
    """
    known, assigned = read or catalogued(poi, cfg, cells)
    k = replace(known)
    r, m = regions.merge_rows(assigned, cfg, weight)
    if len(r) > cfg.dense_regions:
        raise ValueError(f"{len(r)} regions exceed {cfg.dense_regions}: split by tile or raise kappa")
    number = {p: i for i, p in enumerate(k.poi_ids)}
    members = m
    m = m.assign(p=m["poi_id"].map(number)).sort_values("region_id", ascending=False)
    k.encode = np.full((len(k.poi_ids), 24), -1)
    k.encode[m["p"], m["hour"]] = m["region_id"]
    pairs = m[["region_id", "p"]].drop_duplicates().sort_values(["region_id", "p"])
    k.region_members = np.split(pairs["p"].to_numpy(), np.searchsorted(pairs["region_id"].to_numpy(), np.arange(1, len(r))))
    per = 60 // cfg.gt_min
    k.region_slots = [np.arange(a * per, min(b * per, cfg.slots)) for a, b in zip(r["t_start"], r["t_end"])]
    d_s, d_c = haversine_matrix(r["clat"].to_numpy(), r["clon"].to_numpy()), category_matrix(r["node"].tolist())
    d_t = np.minimum(np.abs(r["tmid"].to_numpy()[:, None] - r["tmid"].to_numpy()), TIME_CAP_H)
    k.D = {"all": np.sqrt(d_s**2 + d_t**2 + d_c**2), "space": d_s}[cfg.metric]
    k.diameter = float(k.D.max()) or 1.0
    k.A = edge_matrix(k, r, cfg)
    k.box = np.array([[k.lat[g].min(), k.lat[g].max(), k.lon[g].min(), k.lon[g].max()] for g in k.region_members])
    k.regions, k.members = r, members
    return k


def edge_matrix(k: Knowledge, r, cfg: Cfg) -> np.ndarray:
    """Which region may follow which; least member distances are taken once per pair of distinct place sets."""
    _, first, back = np.unique(r["set_id"].to_numpy(), return_index=True, return_inverse=True)
    sets = [k.region_members[i] for i in first.tolist()]
    members, starts = np.concatenate(sets), np.cumsum([0, *[len(s) for s in sets[:-1]]])
    least = np.array([np.minimum.reduceat(k.km[s].min(axis=0)[members], starts) for s in sets])
    per = 60 // cfg.gt_min
    gap = (r["t_end"].to_numpy() * per - 1)[None, :] - (r["t_start"].to_numpy() * per)[:, None]
    km = least[np.ix_(back, back)].round(9)
    limit = {"gap": gap * cfg.gt_min * cfg.speed_kmh / 60, "slot": np.full_like(gap, cfg.gt_min * cfg.speed_kmh / 60, dtype=float), "fixed": np.full(gap.shape, cfg.theta_fixed_km), "inf": np.full(gap.shape, np.inf)}[cfg.theta]
    return (gap >= 1) & (km <= limit)


def edges_frame(k: Knowledge, poi: DataFrame, cfg: Cfg) -> DataFrame:
    """The edges as a table, by the DataFrame plan."""
    frame = poi.sparkSession.createDataFrame
    sets = frame(k.members.merge(k.regions[["region_id", "set_id"]], on="region_id")[["set_id", "poi_id"]].drop_duplicates())
    return reach.region_edges(frame(k.regions), reach.set_gaps(sets, poi), cfg)
