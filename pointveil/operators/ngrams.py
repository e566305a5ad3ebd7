"""Feasible n-grams: materialised by joins, counted by a path programme, or expanded on the fly."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def count_paths(nodes: DataFrame, edges: DataFrame, n: int) -> DataFrame:
    """One row n, n_grams: how many n-grams there are, without making them."""
    ends = nodes.select(F.col("region_id").alias("src"), F.lit(1).cast("decimal(38,0)").alias("ways"))
    for _ in range(n - 1):
        ends = ends.join(edges, "src").groupBy(F.col("dst").alias("src")).agg(F.sum("ways").cast("decimal(38,0)").alias("ways"))
    return ends.agg(F.sum("ways").cast("double").alias("n_grams")).select(F.lit(n).alias("n"), "n_grams")


def enumerate_grams(nodes: DataFrame, edges: DataFrame, n: int, most: float = 5e7) -> DataFrame:
    """(gram array<long>) of all feasible n-grams; refuses sets larger than ``most``."""
    size = count_paths(nodes, edges, n).first().n_grams or 0
    if size > most:
        raise ValueError(f"{size:.3g} {n}-grams exceed {most:.3g}; use the factored sampler")
    out = nodes.select(F.array(F.col("region_id")).alias("gram"))
    for _ in range(n - 1):
        out = out.withColumn("src", F.element_at("gram", -1)).join(edges, "src").select(F.concat("gram", F.array("dst")).alias("gram"))
    return out


def successors(edges: DataFrame, n_nodes: int, most: int = 200_000_000) -> tuple[np.ndarray, np.ndarray]:
    """Row pointers and successor ids of a public edge table whose size is checked before it comes to the driver."""
    size = edges.count()
    if size > most:
        raise ValueError(f"{size} edges exceed {most}: split the public graph by tile first")
    rows = edges.select("src", "dst").toPandas().sort_values(["src", "dst"])
    counts = np.bincount(rows["src"].to_numpy(dtype=np.int64), minlength=n_nodes)
    return np.concatenate([[0], counts.cumsum()]), rows["dst"].to_numpy(dtype=np.int64)


def refresh(edges: DataFrame, touched: DataFrame, fresh: DataFrame) -> DataFrame:
    """Edges after a public change: those at touched regions (region_id) are replaced by ``fresh``."""
    t = touched.select(F.col("region_id").alias("r"))
    kept = edges.join(t, F.col("src") == F.col("r"), "left_anti").join(t, F.col("dst") == F.col("r"), "left_anti")
    return kept.unionByName(fresh.select("src", "dst"))
