"""Byte-level BPE by speculation and verification.

A word's tokens are first proposed by greedy longest match. A token row is what merging by rank gives if and only
if every adjacent pair is compatible: no merge of lower rank (or of equal rank further left) crosses their border
while the two are built. Borders of all new words are tested together, vectorised over distinct token pairs;
words with a failing pair are merged exactly. Vocabulary, ranks and the special token come from the public
tokenizer file, whose path is a parameter; nothing is trained.
"""

from __future__ import annotations

import hashlib
import heapq
import json
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import byte_chunks

#: The split pattern of byte-level tokenizers (a fixed value of the format).
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
# The library's letters and numbers are those of Unicode 16. Code point ranges (first, last) that came
# with 16 itself, and ranges that only later versions call letters or numbers.
LETTERS_16 = (
    (0x1C89, 0x1C8A), (0xA7CB, 0xA7CD), (0xA7DA, 0xA7DC), (0x105C0, 0x105F3), (0x10D4A, 0x10D65), (0x10D6F, 0x10D85), (0x10EC2, 0x10EC4),
    (0x11380, 0x11389), (0x1138B, 0x1138B), (0x1138E, 0x1138E), (0x11390, 0x113B5), (0x113B7, 0x113B7), (0x113D1, 0x113D1), (0x113D3, 0x113D3),
    (0x11BC0, 0x11BE0), (0x13460, 0x143FA), (0x16100, 0x1611D), (0x16D40, 0x16D6C), (0x18CFF, 0x18CFF), (0x1E5D0, 0x1E5ED), (0x1E5F0, 0x1E5F0),
)
NUMBERS_16 = ((0x10D40, 0x10D49), (0x116D0, 0x116E3), (0x11BF0, 0x11BF9), (0x16130, 0x16139), (0x16D70, 0x16D79), (0x1CCF0, 0x1CCF9), (0x1E5F1, 0x1E5FA))
LATER = (
    (0x558, 0x558), (0x58B, 0x58C), (0x88F, 0x88F), (0xC5C, 0xC5C), (0xCDC, 0xCDC), (0x208F, 0x208F), (0x209D, 0x209F), (0xA7CE, 0xA7CF),
    (0xA7D2, 0xA7D2), (0xA7D4, 0xA7D4), (0xA7DD, 0xA7DD), (0xA7E2, 0xA7E2), (0xA7F1, 0xA7F1), (0xAB6C, 0xAB6D), (0x107BB, 0x107BF),
    (0x10940, 0x10959), (0x10EC5, 0x10EC7), (0x10ED9, 0x10EEE), (0x11B0A, 0x11B0A), (0x11DB0, 0x11DDB), (0x11DE0, 0x11DE9), (0x11DF1, 0x11DF1),
    (0x1246F, 0x1246F), (0x12475, 0x1247F), (0x12550, 0x12686), (0x16EA0, 0x16EB8), (0x16EBB, 0x16ED3), (0x16FF2, 0x16FF3), (0x16FF4, 0x16FF6),
    (0x187F8, 0x187FF), (0x18CD6, 0x18CDA), (0x18D09, 0x18D20), (0x18D80, 0x18DF2), (0x18E00, 0x19191), (0x191A0, 0x191D2), (0x1B123, 0x1B128),
    (0x1B168, 0x1B168), (0x1D6A6, 0x1D6A6), (0x1DF1F, 0x1DF24), (0x1DF2B, 0x1DF81), (0x1DF90, 0x1DF96), (0x1DFCD, 0x1DFFF), (0x1E6C0, 0x1E6DE),
    (0x1E6E0, 0x1E6E2), (0x1E6E4, 0x1E6E5), (0x1E6E7, 0x1E6ED), (0x1E6F0, 0x1E6F4), (0x1E6FE, 0x1E6FF), (0x2B73A, 0x2B73F), (0x2B81E, 0x2B81E),
    (0x2CEA2, 0x2CEAD), (0x323B0, 0x33479), (0x3D000, 0x3FC3F),
)
#: Words and token pairs that a worker remembers; beyond it they are forgotten and found anew.
MOST_WORDS, MOST_PAIRS, LONG_WORD = 400_000, 1_000_000, 256
#: Bytes of words that a worker remembers.
MOST_WORD_BYTES = 64 << 20


def _class(ranges) -> str:
    return "".join(f"\\U{a:08x}-\\U{b:08x}" for a, b in ranges)


def splitter():
    """The splitting function with the letters and numbers of Unicode 16, whatever version the installed module has."""
    import regex

    letter = rf"[[\p{{L}}{_class(LETTERS_16)}]--[{_class(LATER)}]]"
    number = rf"[[\p{{N}}{_class(NUMBERS_16)}]--[{_class(LATER)}]]"
    other = rf"[[^\s\p{{L}}\p{{N}}{_class(LETTERS_16 + NUMBERS_16)}]||[{_class(LATER)}]]"
    plain = regex.compile(PATTERN).findall
    odd = regex.compile(f"[{_class(LETTERS_16 + NUMBERS_16 + LATER)}]").search
    exact = PATTERN.replace(r"[^\s\p{L}\p{N}]", other).replace(r"\p{L}+", letter + "+", 1).replace(r" ?\p{N}+", f" ?{number}+", 1)
    exact = regex.compile(f"(?V1){exact}").findall

    def split(text: str) -> list[str]:
        return plain(text) if text.isascii() or not odd(text) else exact(text)

    return split


def byte_letters() -> list[str]:
    """The printable letter that stands for each byte in the vocabulary file."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    letters, more = {b: chr(b) for b in plain}, 256
    for b in range(256):
        if b not in letters:
            letters[b] = chr(more)
            more += 1
    return [letters[b] for b in range(256)]


class Bpe:
    """Vocabulary, merges and the caches of one worker."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        back = {c: b for b, c in enumerate(byte_letters())}
        as_bytes = {t: bytes(back[c] for c in t) if all(c in back for c in t) else t.encode() for t in model["vocab"]}
        self.ids = {as_bytes[t]: i for t, i in model["vocab"].items()}
        self.special = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        size = max([*self.ids.values(), *self.special.values()]) + 1
        self.text: list[bytes] = [b""] * size
        for t, i in self.ids.items():
            self.text[i] = t
        for t, i in self.special.items():
            self.text[i] = t.encode()
        # a merge by its pair of ids; ranks as arrays for the pair test
        self.merge: dict[tuple[int, int], tuple[int, int]] = {}
        self.rank_of: dict[tuple[int, int], int] = {}
        self.made: list[int] = []
        self.never = len(model["merges"])
        self.left, self.right = np.full(size, -1), np.full(size, -1)
        keys, ranks = [], []
        born = np.full(size, -1)
        for rank, pair in enumerate(model["merges"]):
            x, y = pair.split(" ") if isinstance(pair, str) else pair
            a, b = self.ids[as_bytes[x]], self.ids[as_bytes[y]]
            new = self.ids[as_bytes[x] + as_bytes[y]]
            self.merge[a, b] = (rank, new)
            self.rank_of[a, b] = rank
            self.made.append(new)
            keys.append(a * size + b)
            ranks.append(rank)
            if born[new] < 0:
                self.left[new], self.right[new], born[new] = a, b, rank
        self.size, self.born = size, born
        order = np.argsort(keys)
        self.keys, self.ranks = np.array(keys)[order], np.array(ranks)[order]
        self.longest = max(map(len, self.ids))
        self.single = [self.ids[bytes([b])] for b in range(256)]
        # tokens that merging their own bytes gives back; others are never proposed
        self.sound = {t: i for t, i in self.ids.items() if len(t) == 1 or (born[i] >= 0 and self.exact(t) == [i])}
        self.words: dict[str | int, list[int]] = {}
        self.word_bytes = 0
        self.pairs: dict[int, bool] = {}
        import regex

        self.split = splitter()
        self.cut = regex.compile("(" + "|".join(regex.escape(s) for s in sorted(self.special, key=len, reverse=True)) + ")").split if self.special else None

    # -- proposals

    def propose(self, word: bytes) -> list[int]:
        """Greedy longest match."""
        out, at, n, get, most = [], 0, len(word), self.sound.get, self.longest
        while at < n:
            for end in range(min(n, at + most), at, -1):
                token = get(word[at:end])
                if token is not None:
                    out.append(token)
                    at = end
                    break
        return out

    # -- verification

    def _rank(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Rank of merging a and b; a large number if they don't merge."""
        key = a * self.size + b
        at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        return np.where(self.keys[at] == key, self.ranks[at], np.iinfo(np.int64).max)

    def compatible(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Whether merging the bytes of each pair of tokens gives that pair.

        The border is walked back in time: the side that was built last is taken apart, and the two tokens then
        at the border must not merge earlier than the one taken apart was built.
        """
        a, b = a.copy(), b.copy()
        ok = np.ones(len(a), dtype=bool)
        never = np.iinfo(np.int64).max
        limit = np.full(len(a), never)
        live = np.arange(len(a))
        while len(live):
            x, y = a[live], b[live]
            rank = self._rank(x, y)
            bad = rank < limit[live]
            ok[live[bad]] = False
            live = live[~bad]
            x, y = a[live], b[live]
            rx, ry = self.born[x], self.born[y]
            open_ = (rx >= 0) | (ry >= 0)
            live, x, y, rx, ry = live[open_], x[open_], y[open_], rx[open_], ry[open_]
            # the later of the two is undone; of equals the right one was built last
            first = rx > ry
            # a border merge must come before the undone merge: on the left of it (undoing the right side) equal ranks win too
            limit[live] = np.where(first, rx, ry + 1)
            b[live] = np.where(first, y, self.left[y])
            a[live] = np.where(first, self.right[x], x)
        return ok

    # -- exact merging

    def exact(self, word: bytes) -> list[int]:
        """Merging by rank, leftmost first."""
        parts = [self.single[c] for c in word]
        if len(parts) <= LONG_WORD:
            get, made, never = self.rank_of.get, self.made, self.never
            ranks = [get(p, never) for p in zip(parts, parts[1:])]
            while ranks and (best := min(ranks)) < never:
                i = ranks.index(best)
                parts[i] = made[best]
                del parts[i + 1], ranks[i]
                if i:
                    ranks[i - 1] = get((parts[i - 1], parts[i]), never)
                if i < len(ranks):
                    ranks[i] = get((parts[i], parts[i + 1]), never)
            return parts
        n = len(parts)
        after, before, gone = list(range(1, n + 1)), list(range(-1, n - 1)), bytearray(n)
        heap = [(m[0], i, parts[i], parts[i + 1]) for i in range(n - 1) if (m := self.merge.get((parts[i], parts[i + 1])))]
        heapq.heapify(heap)
        while heap:
            _, i, x, y = heapq.heappop(heap)
            j = after[i]
            if gone[i] or j >= n or parts[i] != x or parts[j] != y:
                continue
            parts[i] = self.merge[x, y][1]
            gone[j] = 1
            k = after[i] = after[j]
            if k < n:
                before[k] = i
                if m := self.merge.get((parts[i], parts[k])):
                    heapq.heappush(heap, (m[0], i, parts[i], parts[k]))
            if (h := before[i]) >= 0 and (m := self.merge.get((parts[h], parts[i]))):
                heapq.heappush(heap, (m[0], h, parts[h], parts[i]))
        return [p for p, g in zip(parts, gone) if not g]

    # -- texts

    def learn(self, words: list[str]) -> int:
        """Fill the word cache for new words; returns how many needed exact merging."""
        raw = [w.encode() for w in words]
        rows = [self.propose(w) for w in raw]
        size = self.size
        keys = {a * size + b for row in rows for a, b in zip(row, row[1:])}
        fresh = np.fromiter((k for k in keys if k not in self.pairs), dtype=np.int64)
        if len(fresh):
            if len(self.pairs) + len(fresh) > MOST_PAIRS:
                self.pairs.clear()
                fresh = np.fromiter(keys, dtype=np.int64)
            self.pairs.update(zip(fresh.tolist(), self.compatible(fresh // size, fresh % size).tolist()))
        pairs, redone = self.pairs, 0
        for word, w, row in zip(words, raw, rows):
            if not all([pairs[a * size + b] for a, b in zip(row, row[1:])]):
                row = self.exact(w)
                redone += 1
            self.words[word] = row
        return redone

    def encode_batch(self, texts: list[str]) -> list[list[int]]:
        """Ids of whole texts; special tokens in a text are themselves."""
        split, special = self.split, self.special
        pieces: list[list] = []
        for t in texts:
            if self.cut is None or not any(s in t for s in special):
                pieces.append(split(t))
            else:
                row: list = []
                for k, part in enumerate(self.cut(t)):
                    row += [special[part]] if k % 2 else split(part)
                pieces.append(row)
        if len(self.words) > MOST_WORDS or self.word_bytes > MOST_WORD_BYTES:
            self.words.clear()
            self.word_bytes = 0
        known = self.words
        fresh = [w for w in set().union(*pieces) if w not in known and isinstance(w, str)]
        if fresh:
            self.learn(fresh)
            self.word_bytes += sum(map(len, fresh))
        for number in special.values():
            known[number] = [number]
        return [list(chain.from_iterable(map(known.__getitem__, row))) for row in pieces]

    def decode(self, ids: list[int]) -> str:
        """The text of ids; bytes that are no UTF-8 become the replacement sign."""
        text = self.text
        return b"".join([text[i] for i in ids]).decode("utf-8", errors="replace")


_HELD: dict[str, Bpe] = {}


def held(path: str) -> Bpe:
    """One vocabulary per worker process."""
    if path not in _HELD:
        _HELD[path] = Bpe(path)
    return _HELD[path]


def encode_column(docs: DataFrame, path: str) -> DataFrame:
    """(doc_id, ids array<int>) of whole texts; null counts as empty."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = held(path)
        for batch in batches:
            for part in byte_chunks(batch, limit=1 << 20):
                ids = bpe.encode_batch([t or "" for t in part.column("text").to_pylist()])
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(ids, pa.list_(pa.int32()))], ["doc_id", "ids"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, ids array<int>")


def decode_column(coded: DataFrame, path: str) -> DataFrame:
    """(doc_id, text) of (doc_id, ids) rows; null ids give null."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = held(path)
        for batch in batches:
            texts = [None if ids is None else bpe.decode(ids) for ids in batch.column("ids").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(texts, pa.string())], ["doc_id", "text"])

    return coded.select(F.col("doc_id").cast("long").alias("doc_id"), "ids").mapInArrow(run, "doc_id long, text string")


def round_trip(docs: DataFrame, path: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256: encode and decode in one pass over the text.

    One row per input row: repeated and null ids and equal rows stay separate, other columns are not read. Null and
    empty texts have no tokens. An empty table gives an empty result.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = held(path)
        for batch in batches:
            for part in byte_chunks(batch, limit=1 << 20):
                rows = bpe.encode_batch([t or "" for t in part.column("text").to_pylist()])
                yield pa.RecordBatch.from_arrays([
                    part.column("doc_id"), pa.array([len(r) for r in rows], pa.int64()),
                    pa.array([hashlib.sha256(np.array(r, dtype="<u4").tobytes()).hexdigest() for r in rows], pa.string()),
                    pa.array([hashlib.sha256(bpe.decode(r).encode()).hexdigest() for r in rows], pa.string()),
                ], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
