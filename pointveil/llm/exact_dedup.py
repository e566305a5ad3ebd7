"""Exact duplicates by deterministic block naming.

Every text is cut into fixed-size byte blocks. Distinct blocks are sorted and get integer names; then adjacent
names are paired, distinct pairs are sorted and named, level by level, until each text has one name. Equal names
mean equal bytes: a block's 64-bit key only routes it, and keys that turn out to stand for two different blocks
are named by their content. Block bytes cross the network once, after map-side combining of repeats.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import free_name, row_key, staged

BLOCK_BYTES = 4096


def _blocks(data: Column, size: int) -> Column:
    last = F.greatest(F.ceil(F.octet_length(data) / size), F.lit(1)) - 1
    return F.transform(F.sequence(F.lit(0), last.cast("int")), lambda i: F.substr(data, i * size + 1, F.lit(size)))


def _level(level: int) -> Column:
    """Names of different levels never meet: the level is in the top bits."""
    return F.lit(level << 56) + F.monotonically_increasing_id()


def block_names(docs: DataFrame, size: int = BLOCK_BYTES, key: Callable[[Column], Column] = F.xxhash64) -> DataFrame:
    """(doc_id, row_no, text_sha256, name): the collision-free identity of every row's whole text.

    Null texts are empty ones; equal rows stay separate rows. ``row_no`` tells repeated ids apart.
    """
    data = F.coalesce(F.col("text"), F.lit("")).cast("binary")
    cut = docs.select("doc_id", data.alias("data")).select("doc_id", F.sha2("data", 256).alias("text_sha256"), _blocks(F.col("data"), size).alias("blocks"))
    heads = staged(cut.select("doc_id", F.monotonically_increasing_id().alias("row_no"), "text_sha256", F.transform("blocks", lambda b: key(b)).alias("keys")))
    single = cut.select(F.explode("blocks").alias("block")).select(key(F.col("block")).alias("key"), "block")
    spread = single.groupBy("key").agg(F.min("block").alias("lo"), F.max("block").alias("hi"))
    named = staged(
        spread.select("key", "lo", (F.col("lo") != F.col("hi")).alias("shared")).sortWithinPartitions("key").select("key", "shared", _level(0).alias("name"))
    )
    rows = heads.select("row_no", F.posexplode("keys").alias("idx", "key"))
    level0 = rows.join(named, "key")
    if not named.where("shared").isEmpty():
        level0 = level0.where(~F.col("shared")).select("row_no", "idx", "name").unionByName(_by_content(docs, named, heads, size, key))
    current = staged(level0.select("row_no", "idx", "name"))
    level, done = 0, []
    while (current.agg(F.max("idx").alias("m")).first().m or 0) > 0:
        level += 1
        wide = current.groupBy("row_no", F.floor(F.col("idx") / 2).cast("int").alias("idx")).agg(
            F.max(F.when(F.col("idx") % 2 == 0, F.col("name"))).alias("a"), F.max(F.when(F.col("idx") % 2 == 1, F.col("name"))).alias("b")
        )
        wide = staged(wide)
        pairs = staged(wide.where("b IS NOT NULL").groupBy("a", "b").agg(F.lit(1).alias("one")).sortWithinPartitions("a", "b").select("a", "b", _level(level).alias("up")))
        joined = wide.join(pairs, ["a", "b"], "left").select("row_no", "idx", F.coalesce("up", "a").alias("name"))
        current = staged(joined)
    return heads.select("doc_id", "row_no", "text_sha256").join(current.select("row_no", "name"), "row_no")


def _by_content(docs: DataFrame, named: DataFrame, heads: DataFrame, size: int, key: Callable[[Column], Column]) -> DataFrame:
    """Level-0 names of blocks whose key is shared by different contents: found by the bytes themselves."""
    odd = named.where("shared").select("key")
    data = F.coalesce(F.col("text"), F.lit("")).cast("binary")
    cut = docs.select("doc_id", F.sha2(data, 256).alias("text_sha256"), F.posexplode(_blocks(data, size)).alias("idx", "block"))
    mine = cut.withColumn("key", key(F.col("block"))).join(odd, "key", "left_semi")
    top = F.lit(1 << 55)
    names = staged(mine.groupBy("block").agg(F.lit(1).alias("one")).sortWithinPartitions("block").select("block", (top + F.monotonically_increasing_id()).alias("name")))
    texts = mine.select("text_sha256", "idx", "block").distinct().join(names, "block").select("text_sha256", "idx", "name")
    return heads.select("row_no", "text_sha256").join(texts, "text_sha256").select("row_no", "idx", "name")


def dedup(docs: DataFrame, size: int = BLOCK_BYTES, key: Callable[[Column], Column] = F.xxhash64) -> DataFrame:
    """One row per input row: doc_id, keep_id, group_size, kept, text_sha256.

    Of equal texts the largest doc_id stays (of repeated ids one row); null ids lose to others. An empty
    table gives an empty result.
    """
    named = staged(block_names(docs, size, key))
    groups = named.groupBy("name").agg(F.max("doc_id").alias("keep_id"), F.count(F.lit(1)).alias("group_size"), F.max(F.struct("doc_id", "row_no")).alias("top"))
    return named.join(groups, "name").select(
        "doc_id", "keep_id", F.col("group_size").cast("long").alias("group_size"), (F.col("row_no") == F.col("top.row_no")).alias("kept"), "text_sha256"
    )


def one_of_equals(docs: DataFrame, size: int = BLOCK_BYTES) -> DataFrame:
    """The rows of ``docs`` but for exact duplicates: of equal texts the row with the largest doc_id stays.

    Null ids lose to others; rows equal in id and text are one. Null and empty texts are equal. An empty table gives
    an empty result. All columns are kept, whatever their names.
    """
    key = free_name(docs, "key")
    kept = dedup(docs, size).where("kept").select(row_key(F.col("doc_id"), F.col("text_sha256")).alias(key))
    sha = F.sha2(F.coalesce(F.col("text"), F.lit("")).cast("binary"), 256)
    keyed = docs.select("*", row_key(F.col("doc_id"), sha).alias(key))
    return keyed.hint("merge").join(kept, key, "left_semi").dropDuplicates([key]).select(*docs.columns)
