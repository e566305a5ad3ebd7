"""Length-bucketed packing: exact dynamic programme over the global length histogram, then token-budget batches.

Texts longer than ``max_len`` tokens become pieces of ``max_len`` and one remainder, so the histogram has at
most ``max_len + 1`` entries however large the corpus is. Null and empty texts are one piece of zero tokens.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .common import staged

MAX_LEN, BUCKETS, BUDGET = 2048, 8, 16384
#: Fewest rows that are numbered together, and most slices a bucket is cut into (bounds the offsets' broadcast).
SLICE_ROWS, MOST_SLICES = 2000, 16384


def optimal_boundaries(histogram: dict[int, int], buckets: int) -> list[int]:
    """Upper bounds of at most ``buckets`` length ranges that minimise total padding over the histogram."""
    lens = np.array(sorted(k for k, v in histogram.items() if v > 0), dtype=np.int64)
    if not len(lens):
        return [1]
    cnt = np.array([histogram[int(k)] for k in lens], dtype=np.float64)
    c, s = np.concatenate([[0.0], cnt.cumsum()]), np.concatenate([[0.0], (cnt * lens).cumsum()])
    m = len(lens)
    # waste[i, j]: padding if lengths i..j share the bound lens[j]; no bound is below one token
    waste = np.maximum(lens, 1)[None, :] * (c[None, 1:] - c[:m, None]) - (s[None, 1:] - s[:m, None])
    waste[np.tril_indices(m, -1)] = np.inf
    best, cuts = waste[0], []
    for _ in range(min(buckets, m) - 1):
        total = best[:-1, None] + waste[1:, :]
        pick = total.argmin(axis=0)
        better = total[pick, np.arange(m)]
        # where one more bucket gains nothing the earlier round's cut holds; 0 is one bucket from the start
        cuts.append(np.where(better < best, pick + 1, cuts[-1] if cuts else 0))
        best = np.minimum(best, better)
    out, j = [], m
    for cut in reversed(cuts):
        out.append(int(lens[j - 1]))
        j = int(cut[j - 1])
        if j == 0:
            break
    if j:
        out.append(int(lens[j - 1]))
    return sorted(max(1, x) for x in set(out))


def pieces(docs: DataFrame, max_len: int = MAX_LEN) -> DataFrame:
    """(doc_id, piece, n_tokens): white-space words of the whole text, cut at ``max_len``."""
    n = F.regexp_count(F.coalesce(F.col("text"), F.lit("")), F.lit(r"[^\x20\x09-\x0D]+")).cast("long")
    counted = docs.select("doc_id", n.alias("n"))
    last = F.greatest(F.ceil(F.col("n") / max_len), F.lit(1)) - 1
    cut = counted.select("doc_id", "n", F.explode(F.sequence(F.lit(0).cast("long"), last.cast("long"))).alias("piece"))
    return cut.select("doc_id", F.col("piece").cast("int").alias("piece"), F.least(F.lit(max_len), F.col("n") - F.col("piece") * max_len).cast("int").alias("n_tokens"))


def bucket_of(n: Column, bounds: list[int]) -> Column:
    """The least bound that holds ``n`` tokens."""
    return F.coalesce(*[F.when(n <= b, F.lit(b)) for b in bounds])


def pack(docs: DataFrame, max_len: int = MAX_LEN, buckets: int = BUCKETS, budget: int = BUDGET) -> DataFrame:
    """One row per piece: doc_id, piece, n_tokens, bucket_len, batch_id, slot, padding.

    A batch of bucket b holds ``budget // b`` pieces; all batches of a bucket but its last are full. Pieces are
    numbered inside (bucket, slice) windows and shifted by the counts of earlier slices, so no task ever holds
    a whole bucket. Repeated ids are packed as separate rows; an empty table gives an empty result.
    """
    cut = staged(pieces(docs, max_len))
    histogram = {r.n_tokens: r.n for r in cut.groupBy("n_tokens").agg(F.count(F.lit(1)).alias("n")).collect()}
    total = sum(histogram.values())
    bounds = optimal_boundaries(histogram, buckets)
    slices = max(1, min(MOST_SLICES, math.ceil(total / max(SLICE_ROWS, 10 * math.isqrt(total)))))
    placed = cut.select("*", bucket_of(F.col("n_tokens"), bounds).alias("bucket_len"), F.pmod(F.xxhash64("doc_id", "piece"), F.lit(slices)).alias("part"))
    sizes = placed.groupBy("bucket_len", "part").agg(F.count(F.lit(1)).alias("size"))
    before = W.partitionBy("bucket_len").orderBy("part").rowsBetween(W.unboundedPreceding, -1)
    offsets = sizes.select("bucket_len", "part", F.coalesce(F.sum("size").over(before), F.lit(0)).alias("before"))
    here = W.partitionBy("bucket_len", "part").orderBy("doc_id", "piece")
    numbered = placed.withColumn("seq", F.row_number().over(here)).join(F.broadcast(offsets), ["bucket_len", "part"])
    room = F.greatest(F.lit(1), F.floor(F.lit(budget) / F.col("bucket_len"))).cast("long")
    seq = F.col("seq") + F.col("before") - 1
    return numbered.select(
        "doc_id", "piece", "n_tokens", "bucket_len",
        F.concat_ws("-", F.col("bucket_len").cast("string"), F.floor(seq / room).cast("string")).alias("batch_id"),
        (seq % room).cast("int").alias("slot"),
        (F.col("bucket_len") - F.col("n_tokens")).cast("int").alias("padding"),
    )
