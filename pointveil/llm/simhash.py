"""SimHash near-duplicates with a Gray-order hierarchical index.

Fingerprints within ``distance`` differing bits are linked. Distribution: a pair within 3 bits agrees on one of
four 16-bit blocks, so each fingerprint goes to four keys; a key with more than ``hot`` members is cut again by
blocks of its other bits (repeatedly), which keeps every link because the rest differs by at most 3 bits too.
A key still crowded after that is cut into chunks that meet pairwise, so a task's rows stay bounded.
Inside a key the fingerprints are sorted by Gray rank and grouped, eight at a time, into nodes that hold the bits
all members share. A descent over node pairs adds up differences bit group by bit group, drops a pair of nodes
once the sum passes ``distance`` and ties whole nodes together once no member can be farther. Only edges of a
spanning forest leave a task.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import byte_chunks, free_name, row_key, staged, texts_of
from .components import components

DISTANCE, SEED, FAN = 3, 42, 8
#: A key with more members is cut by further bits; rows of whole keys that are indexed together.
HOT_KEY, KEY_ROWS = 20_000, 100_000


def shingle_hashes(text: bytes, width: int) -> list[int]:
    """Unsigned XXH64 of every run of ``width`` words (fewer words: the whole sequence; none: nothing)."""
    words = text.lower().split()
    if not words:
        return []
    digest = xxhash.xxh64_intdigest
    if len(words) <= width:
        return [digest(b" ".join(words), SEED)]
    line = b" ".join(words)
    at, starts = 0, []
    for w in words:
        starts.append(at)
        at += len(w) + 1
    ends = [s - 1 for s in starts[width:]] + [len(line)]
    return [digest(line[a:b], SEED) for a, b in zip(starts, ends)]


def fingerprints_of(texts: list[bytes], width: int) -> np.ndarray:
    """uint64 fingerprints: a bit is 1 if more than half of the shingle hashes set it; no words give 0."""
    per = [shingle_hashes(t, width) for t in texts]
    out = np.zeros(len(texts), dtype=np.uint64)
    sizes = np.array([len(p) for p in per], dtype=np.int64)
    full = np.flatnonzero(sizes)
    if not len(full):
        return out
    flat = np.array([h for p in per for h in p], dtype=np.uint64)
    bits = np.unpackbits(flat.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    counts = np.add.reduceat(bits, np.concatenate([[0], sizes[full].cumsum()[:-1]]), axis=0, dtype=np.int32)
    on = (2 * counts > sizes[full][:, None]).astype(np.uint8)
    out[full] = np.packbits(on, axis=1, bitorder="little").view(np.uint64).ravel()
    return out


def fingerprint_table(docs: DataFrame, width: int) -> DataFrame:
    """(doc_id, fp long): the fingerprint of every row's whole text; null counts as empty."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in byte_chunks(batch):
                fps = fingerprints_of(texts_of(part), width)
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(fps.view(np.int64))], ["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, fp long")


def gray_rank(x: np.ndarray) -> np.ndarray:
    """The position of each fingerprint in the reflected Gray sequence (of a row of words: words, the first is highest)."""
    x = x.copy()
    for s in (1, 2, 4, 8, 16, 32):
        x ^= x >> np.uint64(s)
    for k in range(1, x.shape[1] if x.ndim > 1 else 1):  # an odd number of ones before a word turns it round
        x[:, k] ^= np.uint64(0) - (x[:, k - 1] & np.uint64(1))
    return x


def weight(bits: np.ndarray) -> np.ndarray:
    """Ones of every fingerprint, be it one word or a row of words."""
    ones = np.bitwise_count(bits)
    return ones if ones.ndim == 1 else ones.sum(axis=1, dtype=np.uint64)


class GrayIndex:
    """Hierarchical index over (group, fingerprint) rows; groups are never compared with each other.

    A fingerprint is one word, or a row of words.
    """

    def __init__(self, group: np.ndarray, fp: np.ndarray):
        rank = gray_rank(fp)
        order = np.lexsort((*(rank[:, None] if rank.ndim == 1 else rank).T[::-1], group))
        self.order, self.fp = order, fp[order]
        group = group[order]
        ones, none = np.full(fp.shape, np.uint64(0xFFFFFFFFFFFFFFFF)), np.zeros(len(fp), dtype=np.int64)
        # a level: first child, number of children, shared mask, shared pattern, first and last row
        row = np.arange(len(fp))
        self.levels = [(none, none, ones, self.fp, row, row)]
        while True:
            _, _, mask, pattern, first, last = self.levels[-1]
            starts_group = np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1]]))
            if len(starts_group) == len(group):
                break
            rank = np.arange(len(group)) - np.repeat(starts_group, np.diff(np.append(starts_group, len(group))))
            starts = np.flatnonzero(rank % FAN == 0)
            size = np.diff(np.append(starts, len(group)))
            all_on = np.bitwise_and.reduceat(pattern & mask, starts)
            all_off = np.bitwise_and.reduceat(~pattern & mask, starts)
            self.levels.append((starts, size, all_on | all_off, all_on, first[starts], last[starts + size - 1]))
            group = group[starts]

    def links(self, distance: int, step: int = 8192, closure: bool = True) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Pairs of input row numbers within ``distance``: all of them, or (closure) enough to connect the same rows."""
        top = len(self.levels) - 1
        n = len(self.levels[top][0])
        root, zero, seen = np.arange(n), np.zeros(n, dtype=np.uint64), np.zeros((n, *self.fp.shape[1:]), dtype=np.uint64)
        todo = [(top, root[i : i + step], root[i : i + step], seen[i : i + step], zero[i : i + step]) for i in range(0, n, step)]
        offsets = np.arange(FAN)
        while todo:
            level, a, b, seen, apart = todo.pop()
            if level == 0:
                real = a != b
                yield self.order[a[real]], self.order[b[real]]
                continue
            first, size, *_ = self.levels[level]
            i = np.broadcast_to(offsets[None, :, None], (len(a), FAN, FAN))
            j = np.broadcast_to(offsets[None, None, :], (len(a), FAN, FAN))
            ok = (i < size[a][:, None, None]) & (j < size[b][:, None, None]) & ((a != b)[:, None, None] | (i <= j))
            at = np.nonzero(ok)
            x, y, up = first[a][at[0]] + at[1], first[b][at[0]] + at[2], at[0]
            _, _, mask, pattern, low, high = self.levels[level - 1]
            comparable = mask[x] & mask[y]
            total = apart[up] + weight((pattern[x] ^ pattern[y]) & comparable & ~seen[up])
            near = total <= distance
            whole = near & (total + weight(~comparable) <= distance) & (level > 1 and closure)
            if whole.any():
                yield from self._tied(low[x[whole]], high[x[whole]], low[y[whole]], high[y[whole]])
            go = np.flatnonzero(near & ~whole)
            for k in range(0, len(go), step):
                s = go[k : k + step]
                todo.append((level - 1, x[s], y[s], comparable[s], total[s]))

    def _tied(self, a0, a1, b0, b1) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Every member of the one node is near every member of the other: two stars tie them."""
        for lo, hi, to in ((a0, a1, b0), (b0, b1, a0)):
            size = hi - lo + 1
            to = np.repeat(to, size)
            own = np.arange(size.sum()) - np.repeat(size.cumsum() - size, size) + np.repeat(lo, size)
            real = own != to
            yield self.order[own[real]], self.order[to[real]]


def forest(n: int, pairs: Iterator[tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
    """The least row of each row's component."""
    root = np.arange(n)
    for a, b in pairs:
        while len(a):
            a, b = root[a], root[b]
            apart = a != b
            if not apart.any():
                break
            a, b = a[apart], b[apart]
            np.minimum.at(root, np.maximum(a, b), np.minimum(a, b))
            while True:
                up = root[root]
                if (up == root).all():
                    break
                root = up
    return root


def _edges_of(distance: int):
    def edges(table: pa.Table) -> pa.RecordBatch:
        fp = table.column("fp").to_numpy().view(np.uint64)
        root = forest(len(fp), GrayIndex(table.column("key").to_numpy(), fp).links(distance))
        return _tree(root, fp.view(np.int64))

    return edges


def _tree(root: np.ndarray, node: np.ndarray) -> pa.RecordBatch:
    tied = np.flatnonzero(root != np.arange(len(root)))
    return pa.RecordBatch.from_arrays([pa.array(node[root[tied]]), pa.array(node[tied])], ["a", "b"])


def _by_keys(edges_of):
    """An Arrow mapper that gives ``edges_of`` whole keys of key-sorted rows, about ``KEY_ROWS`` rows at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        rows = 0
        for batch in batches:
            held.append(batch)
            rows += batch.num_rows
            if rows < KEY_ROWS:
                continue
            table = pa.Table.from_batches(held)
            key = table.column("key").to_numpy()
            cut = int(np.searchsorted(key == key[-1], True))  # rows arrive sorted: the last key may go on
            if cut:
                yield edges_of(table.slice(0, cut))
            held = table.slice(cut).combine_chunks().to_batches()
            rows = table.num_rows - cut
        if rows:
            yield edges_of(pa.Table.from_batches(held))

    return run


def _signed(bits: list[int]) -> int:
    m = sum(1 << b for b in bits)
    return m - (1 << 64) if m >> 63 else m


def _masks(bits: list[int], parts: int) -> list[tuple[int, list[int]]]:
    """Cut bit positions into ``parts`` runs: (mask of a run, the bits outside it)."""
    cuts = np.array_split(np.array(bits), parts)
    return [(_signed(c.tolist()), [b for b in bits if b not in set(c.tolist())]) for c in cuts]


def near_pairs(fps: DataFrame, distance: int = DISTANCE, hot: int = HOT_KEY, depth: int = 3) -> DataFrame:
    """Edges (a, b) between distinct fingerprints (column fp) whose closure is that of all pairs within ``distance``.

    Keys are hashes of (path of blocks, value): a hash collision only brings strangers together, and every pair
    is still checked bit by bit.
    """
    parts = distance + 1
    frontier = [(F.lit(0).cast("long"), list(range(64)), fps)]
    rows = None
    for d in range(depth):
        last = d == depth - 1
        level, paths = None, []
        for path, bits, members in frontier:
            for n, (mask, rest) in enumerate(_masks(bits, parts)):
                key = F.xxhash64(path, F.lit(mask), F.col("fp").bitwiseAND(F.lit(mask)))
                paths.append((n, rest))
                one = members.select("fp", key.alias("key"), F.lit(len(paths) - 1).alias("path"))
                level = one if level is None else level.unionByName(one)
        level = staged(level)
        big = crowded(level, hot)
        if big.isEmpty():
            return _joined(rows, level)
        if last:
            return _joined(rows, chunked(level, big, ["fp"]))
        big = big.select("key")
        rows = _joined(rows, level.join(big, "key", "left_anti"))
        kept = staged(level.join(big, "key", "left_semi"))
        frontier = [(F.col("key"), rest, kept.where(F.col("path") == i).select("fp", "key")) for i, (_, rest) in enumerate(paths)]
    return rows


def crowded(rows: DataFrame, hot: int) -> DataFrame:
    """(key, chunks): keys with more than ``hot`` rows and the number of chunks of ``hot / 2`` rows they need."""
    sizes = rows.groupBy("key").agg(F.count(F.lit(1)).alias("n"))
    return sizes.where(F.col("n") > hot).select("key", F.ceil(2 * F.col("n") / hot).alias("chunks"))


def chunked(rows: DataFrame, big: DataFrame, member: list[str]) -> DataFrame:
    """Crowded keys' rows cut into chunks by a hash of ``member``; any two chunks meet under a key of their own.

    Every two rows of a key still share a key, so no pair is lost, and a task holds two chunks at a time.
    """
    count = F.coalesce("chunks", F.lit(1))
    mine, other = F.pmod(F.xxhash64(F.lit(SEED), *member), count), F.col("other")
    apart = F.xxhash64("key", F.least(mine, other), F.greatest(mine, other))
    spread = rows.join(big, "key", "left").withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), count - 1)))
    return spread.withColumn("key", F.when(F.col("chunks").isNull(), F.col("key")).otherwise(apart)).select(*rows.columns)


def _joined(rows: DataFrame | None, more: DataFrame) -> DataFrame:
    more = more.select("fp", "key")
    return more if rows is None else rows.unionByName(more)


def linked(fps: DataFrame, distance: int = DISTANCE, hot: int = HOT_KEY) -> DataFrame:
    """(node, root): components of distinct fingerprints that have a partner within ``distance`` bits."""
    rows = near_pairs(fps, distance, hot).distinct().repartition("key").sortWithinPartitions("key")
    edges = rows.mapInArrow(_by_keys(_edges_of(distance)), "a long, b long")
    return components(edges)


def near_duplicates(docs: DataFrame, width: int = 3, distance: int = DISTANCE, hot: int = HOT_KEY) -> DataFrame:
    """One row per document: doc_id, fingerprint (16 hex digits), component_id, fp_size.

    component_id is the least doc_id reachable over links of at most ``distance`` bits. Equal texts meet in one
    fingerprint before any search. Null and empty texts share fingerprint zero. An empty table gives no rows.
    """
    table = staged(fingerprint_table(docs, width))
    nodes = staged(table.groupBy("fp").agg(F.min("doc_id").alias("low"), F.count(F.lit(1)).alias("fp_size")))
    roots = staged(linked(nodes.select("fp"), distance, hot))
    labelled = nodes.join(roots.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "low", "fp_size", F.coalesce("root", "fp").alias("root"))
    low = labelled.groupBy("root").agg(F.min("low").alias("component_id"))
    per_fp = staged(labelled.join(low, "root").select("fp", "fp_size", "component_id"))
    return table.join(per_fp, "fp").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id", "fp_size")


# ---------------------------------------------------------------- similarity of 0.8 or more

#: Words of 64 bits in a wide fingerprint, and words in a shingle.
WIDE_WORDS, WIDE_WIDTH = 4, 5
WIDE = [f"f{k}" for k in range(WIDE_WORDS)]


def wide_fingerprints(texts: list[bytes], width: int = WIDE_WIDTH) -> np.ndarray:
    """Texts x WIDE_WORDS words: majority bits of four mixes of every shingle hash; no words give zeros."""
    out = np.zeros((len(texts), WIDE_WORDS), dtype=np.uint64)
    per = [shingle_hashes(t, width) for t in texts]
    sizes = np.array([len(p) for p in per], dtype=np.int64)
    full = np.flatnonzero(sizes)
    if not len(full):
        return out
    flat = np.array([h for p in per for h in p], dtype=np.uint64)
    cut = np.concatenate([[0], sizes[full].cumsum()[:-1]])
    for k in range(WIDE_WORDS):
        h = (flat + np.uint64(k * 0x9E3779B97F4A7C15 % (1 << 64))) * np.uint64(0xBF58476D1CE4E5B9)
        h = (h ^ (h >> np.uint64(29))) * np.uint64(0x94D049BB133111EB)
        bits = np.unpackbits((h ^ (h >> np.uint64(32))).view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        counts = np.add.reduceat(bits, cut, axis=0, dtype=np.int32)
        out[full, k] = np.packbits((2 * counts > sizes[full][:, None]).astype(np.uint8), axis=1, bitorder="little").view(np.uint64).ravel()
    return out


#: Keys of a text and least hashes in a key: shingle sets of similarity J share a key with chance 1 - (1 - J^4)^24,
#: which is 0.999997 at 0.8.
KEYS, PER_HASH = 24, 4
#: Candidates differ in at most so many of 256 bits: 39 are expected at a similarity of 0.8, 48 in sets of four and
#: five shingles, and a standard error is about 6.
LOOSE_DISTANCE = 84
#: Bytes of shingle sets of one group that meet in a task; a larger group is compared chunk by chunk.
SET_BYTES = 64 << 20
_DRAW = np.random.default_rng(SEED).integers(0, 1 << 32, (2, KEYS * PER_HASH), dtype=np.uint32)


def key_hashes(texts: list[bytes], width: int = WIDE_WIDTH) -> np.ndarray:
    """Texts x KEYS words: every word mixes the least of PER_HASH orders of the shingles; no words give zeros."""
    out = np.zeros((len(texts), KEYS), dtype=np.uint64)
    per = [shingle_hashes(t, width) for t in texts]
    sizes = np.array([len(p) for p in per], dtype=np.int64)
    full = np.flatnonzero(sizes)
    if not len(full):
        return out
    flat = (np.array([h for p in per for h in p], dtype=np.uint64) >> np.uint64(32)).astype(np.uint32)
    cut = np.concatenate([[0], sizes[full].cumsum()[:-1]])
    for k in range(KEYS):
        mixed = np.full(len(full), k + 1, dtype=np.uint64)
        for n in range(k * PER_HASH, (k + 1) * PER_HASH):
            least = np.minimum.reduceat((flat ^ _DRAW[0, n]) * (_DRAW[1, n] | np.uint32(1)), cut)
            mixed = (mixed ^ least) * np.uint64(0x9E3779B97F4A7C15)
            mixed ^= mixed >> np.uint64(31)
        out[full, k] = mixed
    return out


def _keyed_table(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for part in byte_chunks(batch):
            texts = texts_of(part)
            fps = wide_fingerprints(texts).view(np.int64)
            keys = key_hashes(texts).view(np.int64)
            cols = [part.column("doc_id"), pa.array([hashlib.sha256(t).digest() for t in texts], pa.binary())]
            cols += [*[pa.array(np.ascontiguousarray(fps[:, k])) for k in range(WIDE_WORDS)], pa.array(list(keys), pa.list_(pa.int64()))]
            yield pa.RecordBatch.from_arrays(cols, ["doc_id", "sha", *WIDE, "keys"])


def text_sha(text: Column) -> Column:
    """The identity of a text (binary SHA-256); null counts as empty."""
    return F.unhex(F.sha2(F.coalesce(text, F.lit("")).cast("binary"), 256))


def _loose_edges(distance: int):
    """Edges between rows of a key within ``distance`` bits, found by the Gray-order index over the wide fingerprints."""

    def edges(table: pa.Table) -> pa.RecordBatch:
        key, ids = table.column("key").to_numpy(), table.column("id").to_numpy()
        starts = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
        size = np.diff(np.append(starts, len(key)))
        shared = np.flatnonzero(np.repeat(size, size) > 1)
        if not len(shared):
            return _tree(np.arange(0), ids[:0])
        fps = np.stack([table.column(f).to_numpy()[shared] for f in WIDE], axis=1).view(np.uint64)
        return _tree(forest(len(shared), GrayIndex(key[shared], fps).links(distance)), ids[shared])

    return edges


def text_nodes(docs: DataFrame) -> DataFrame:
    """(id, sha, low, fingerprint, keys): one row per distinct text with words, equal ones met map-side.

    ``low`` is the least doc_id of the text (null only if no row has an id). Ids ascend with (low, sha), nulls last,
    so the least id of a group is the text that stays.
    """
    usable = docs.where(F.coalesce(F.col("text"), F.lit("")).rlike(r"[^\x20\x09-\x0D]"))
    fields = ", ".join(["doc_id long", "sha binary", *[f"{c} long" for c in WIDE], "keys array<long>"])
    table = usable.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(_keyed_table, fields)
    same = table.groupBy("sha").agg(F.min("doc_id").alias("low"), *[F.first(c).alias(c) for c in (*WIDE, "keys")])
    return staged(same.sort(F.col("low").asc_nulls_last(), "sha").select(F.monotonically_increasing_id().alias("id"), "*"))


def loose_groups(nodes: DataFrame, distance: int = LOOSE_DISTANCE, hot: int = HOT_KEY) -> DataFrame:
    """(node, root): components of candidates, which share a key and differ in at most ``distance`` bits.

    The keys only deal the fingerprints to tasks, as the bit blocks of ``near_pairs`` do for smaller distances; the
    Gray-order index finds the pairs inside a key.
    Texts with equal fingerprints and keys are one row of the search; a crowded key is compared chunk by chunk.
    """
    same = [*WIDE, "keys"]
    firsts = staged(nodes.groupBy(*same).agg(F.min("id").alias("id"), F.count(F.lit(1)).alias("n")))
    often = firsts.where("n > 1").withColumnRenamed("id", "a").drop("n")
    equal = nodes.withColumnRenamed("id", "b").join(often.hint("merge"), same).where("a <> b").select("a", "b")
    rows = firsts.select(F.explode("keys").alias("key"), "id", *WIDE)
    rows = chunked(rows, F.broadcast(crowded(rows, hot)), ["id"])
    edges = rows.repartition("key").sortWithinPartitions("key").mapInArrow(_by_keys(_loose_edges(distance)), "a long, b long")
    return components(edges.unionByName(equal))


def _spans(start: np.ndarray, size: np.ndarray) -> np.ndarray:
    """The positions start, start + 1, ... of every span, one after the other."""
    return np.arange(size.sum()) + np.repeat(start - (size.cumsum() - size), size)


def alike_roots(sets: list[np.ndarray]) -> np.ndarray:
    """The component of each set (as the least set number) over pairs whose exact Jaccard similarity is 0.8 or more.

    Such a pair shares one of the rarest fifth (and one more) of either set, so only these are looked up; a pair
    that is in one component already is not compared.
    """
    given = np.array([len(s) for s in sets], dtype=np.int64)
    order = np.argsort(given, kind="stable")
    size = given[order]
    begin = size.cumsum() - size
    _, code, times = np.unique(np.concatenate([sets[i] for i in order]), return_inverse=True, return_counts=True)
    by_rarity = np.empty(len(times), dtype=np.int64)
    by_rarity[np.argsort(times, kind="stable")] = np.arange(len(times))
    code = by_rarity[code]
    code = code[np.lexsort((code, np.repeat(np.arange(len(size)), size)))]
    prefix = size - -(-4 * size // 5) + 1
    looked, owner = code[_spans(begin, prefix)], np.repeat(np.arange(len(size)), prefix)
    by_code = np.argsort(looked, kind="stable")
    post = owner[by_code]
    at = np.searchsorted(looked[by_code], np.arange(len(times) + 1))
    root, mine = np.arange(len(size)), np.zeros(len(times), dtype=bool)
    for i in range(1, len(size)):
        own = code[begin[i] : begin[i] + size[i]]
        head = own[: prefix[i]]
        found = np.zeros(len(size), dtype=bool)
        found[post[_spans(at[head], at[head + 1] - at[head])]] = True
        others = np.flatnonzero(found[:i] & (5 * size[:i] >= 4 * size[i]))
        mine[own] = True
        step = 8
        while len(others := others[root[others] != root[i]]):
            now, others = others[:step], others[step:]
            shared = np.add.reduceat(mine[code[_spans(begin[now], size[now])]], size[now].cumsum() - size[now], dtype=np.int64)
            for j in now[9 * shared >= 4 * (size[now] + size[i])]:
                root[root == max(root[i], root[j])] = min(root[i], root[j])
            step *= 2
        mine[own] = False
    out = np.empty(len(size), dtype=np.int64)
    least = np.full(len(size), len(size))
    np.minimum.at(least, root, order)
    out[order] = least[root]
    return out


def _set_table(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for part in byte_chunks(batch):
            sets = [np.unique(np.array(shingle_hashes(t, WIDE_WIDTH), dtype=np.uint64)).tobytes() for t in texts_of(part)]
            yield pa.RecordBatch.from_arrays([part.column("key"), part.column("id"), pa.array(sets, pa.binary())], ["key", "id", "shingles"])


def _alike_edges(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Edges of a spanning forest of every key; rows arrive sorted by key, and one key is held at a time."""
    key, ids, sets = None, [], []

    def out() -> pa.RecordBatch:
        return _tree(alike_roots(sets), np.array(ids, dtype=np.int64))

    for batch in batches:
        for k, n, shingles in zip(*(batch.column(c).to_pylist() for c in ("key", "id", "shingles"))):
            if k != key and len(ids) > 1:
                yield out()
            if k != key:
                key, ids, sets = k, [], []
            ids.append(n)
            sets.append(np.frombuffer(shingles, dtype=np.uint64))
    if len(ids) > 1:
        yield out()


def alike_nodes(docs: DataFrame, nodes: DataFrame, hot: int = HOT_KEY, most: int = SET_BYTES) -> DataFrame:
    """(node, root): components, by least node id, of distinct texts whose five-word shingle sets are 0.8 or more alike.

    Fingerprints and keys only find the groups inside which all pairs are held against each other; an edge needs
    an exact Jaccard similarity of 0.8.
    """
    loose = loose_groups(nodes, hot=hot).select(F.col("node").alias("id"), F.col("root").alias("key"))
    asked = staged(nodes.select("id", "sha", "low").join(loose.hint("merge"), "id").select("id", "key", "sha", "low"))
    texts = docs.select(F.col("doc_id").cast("long").alias("low"), text_sha(F.col("text")).alias("sha"), "text")
    # one row of every asked text: that of its least id (equal rows give equal sets, of which one is kept)
    rows = texts.hint("merge").join(asked, texts["low"].eqNullSafe(asked["low"]) & (texts["sha"] == asked["sha"])).select("key", "id", "text")
    rows = staged(rows.mapInArrow(_set_table, "key long, id long, shingles binary").dropDuplicates(["key", "id"]))
    bytes_ = F.sum(F.octet_length("shingles"))
    big = rows.groupBy("key").agg(bytes_.alias("n")).where(F.col("n") > most).select("key", F.ceil(2 * F.col("n") / most).alias("chunks"))
    rows = chunked(rows, F.broadcast(big), ["id"])
    return components(rows.repartition("key").sortWithinPartitions("key").mapInArrow(_alike_edges, "a long, b long"))


def alike_groups(docs: DataFrame, hot: int = HOT_KEY, most: int = SET_BYTES) -> DataFrame:
    """(node, root) by doc_id of the groups of ``alike_nodes``: each text's least id and that of its group's first text."""
    nodes = text_nodes(docs)
    names = nodes.select("id", "low")
    groups = alike_nodes(docs, nodes, hot, most)
    return (
        groups.join(names.select(F.col("id").alias("node"), F.col("low").alias("n")), "node")
        .join(names.select(F.col("id").alias("root"), F.col("low").alias("r")), "root")
        .select(F.col("n").alias("node"), F.col("r").alias("root"))
    )


def one_of_each(docs: DataFrame, hot: int = HOT_KEY, most: int = SET_BYTES) -> DataFrame:
    """The rows of ``docs`` but for near duplicates: of each group of texts that are 0.8 or more alike one row stays.

    The row that stays has the least doc_id (null ids last; of one id the text with the least SHA-256). Rows equal in
    id and text are one document. Rows of one id with other texts are documents of their own. Texts without words
    (null, empty, blank) are in no group and stay. An empty table gives an empty result. All columns are kept,
    whatever their names.
    """
    nodes = text_nodes(docs)
    gone = alike_nodes(docs, nodes, hot, most).where("node <> root").select(F.col("node").alias("id"))
    stays = nodes.join(gone.hint("merge"), "id", "left_anti").select("low", "sha")
    key = free_name(docs, "key")
    stays = stays.select(row_key(F.col("low"), F.lower(F.hex("sha"))).alias(key))
    wordy = F.coalesce(F.col("text"), F.lit("")).rlike(r"[^\x20\x09-\x0D]")
    mine = row_key(F.col("doc_id").cast("long"), F.sha2(F.coalesce(F.col("text"), F.lit("")).cast("binary"), 256))
    keyed = docs.select("*", F.when(wordy, mine).alias(key))
    kept = keyed.where(F.col(key).isNotNull()).hint("merge").join(stays, key, "left_semi").dropDuplicates([key])
    return kept.unionByName(keyed.where(F.col(key).isNull())).select(*docs.columns)
