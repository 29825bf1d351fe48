"""Byte-level BPE encoding and decoding with length-bucketed padded numpy matrices.

New words of a batch are bucketed by length; a bucket is one matrix of token ids, a row per word.
Each round every row merges its leftmost pair of minimum rank: pair ranks come from an open-
addressing hash table, the merged row is compacted by one place and only the two pairs beside the
merge are looked up again.  Rows without a mergeable pair leave the matrix.  Words beyond
``LONG`` bytes merge by a heap over a linked list instead, so that one huge word stays
n log n; both take the same merges in the same order.

Words met before are looked up in a bounded memo.  Defined results: a null text is the empty one
and has no ids; any text decodes to its own UTF-8 bytes.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
import re
from functools import cache, partial

import numpy as np
import regex
from pyspark.sql import DataFrame, SparkSession, types as T

from polyedge.llm import common

NONE = np.int32(2**31 - 1)
LONG = 512
MEMO_ENTRIES = 300_000
ODD_SPACE = re.compile(r"[^\S\n ]|[ \n][ \n]|^[ \n]|[ \n]\Z")


def read_ranks(spark: SparkSession | None, path: str) -> dict[bytes, int]:
    """Ranks of a vocabulary file: a base64 token and its rank on each line."""
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}


class PairTable:
    """Open-addressing hash table from a pair of token ids to the id they merge into."""

    def __init__(self, left: np.ndarray, right: np.ndarray, merged: np.ndarray):
        self.shift = np.uint64(64 - max(4, int(len(merged) * 2.5).bit_length()))
        size = 1 << (64 - int(self.shift))
        self.mask = size - 1
        self.keys = np.full(size, -1, np.int64)
        self.values = np.full(size, NONE, np.int32)
        key = (left.astype(np.int64) << 32) | right.astype(np.int64)
        slot = self._slot(key)
        waiting = np.arange(len(key))
        self.probes = 1
        while len(waiting):
            free = waiting[self.keys[slot[waiting]] == -1]
            _, first = np.unique(slot[free], return_index=True)
            placed = free[first]
            self.keys[slot[placed]] = key[placed]
            self.values[slot[placed]] = merged[placed]
            waiting = np.setdiff1d(waiting, placed, assume_unique=True)
            slot[waiting] = (slot[waiting] + 1) & self.mask
            self.probes += bool(len(waiting))

    def _slot(self, key: np.ndarray) -> np.ndarray:
        return ((key.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> self.shift).astype(np.int64)

    def find(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Merged ids, ``NONE`` where the pair does not merge (ids below zero never do)."""
        key = (left.astype(np.int64) << 32) | (right.astype(np.int64) & 0xFFFFFFFF)
        slot = self._slot(key)
        out = np.full(len(key), NONE, np.int32)
        at = np.flatnonzero((left >= 0) & (right >= 0))
        for _ in range(self.probes + 1):
            held = self.keys[slot[at]]
            hit = held == key[at]
            out[at[hit]] = self.values[slot[at[hit]]]
            at = at[~hit & (held != -1)]
            if not len(at):
                break
            slot[at] = (slot[at] + 1) & self.mask
        return out


class Vocabulary:
    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.ranks = ranks
        self.split = regex.compile(pattern)
        self.token_bytes: list[bytes] = [b""] * (max(ranks.values()) + 1)
        left, right, merged = [], [], []
        for token, rank in ranks.items():
            self.token_bytes[rank] = token
            for i in range(1, len(token)):
                a = ranks.get(token[:i])
                if a is not None and (b := ranks.get(token[i:])) is not None:
                    left.append(a)
                    right.append(b)
                    merged.append(rank)
        self.pairs = PairTable(np.array(left, np.int32), np.array(right, np.int32), np.array(merged, np.int32))
        self.byte_id = np.array([ranks[bytes([i])] for i in range(256)], np.int32)
        self.words: dict[str, bytes] = {}
        self.chunks: dict[str, bytes] = {}

    def merge_matrix(self, m: np.ndarray) -> np.ndarray:
        """All merges of rows padded with -1; ids stay to the left."""
        out = np.full_like(m, -1)
        rows = np.arange(len(m))
        width = m.shape[1]
        r = self.pairs.find(m[:, :-1].ravel(), m[:, 1:].ravel()).reshape(len(m), width - 1)
        while len(rows):
            at = r.argmin(1)  # the first of the least ranks
            k = np.arange(len(rows))
            best = r[k, at]
            on = best != NONE
            if not on.all():
                out[rows[~on], : m.shape[1]] = m[~on]
                m, r, rows, at, best = m[on], r[on], rows[on], at[on], best[on]
                if not len(rows):
                    break
                k = np.arange(len(rows))
            m[k, at] = best
            width = m.shape[1]
            place = np.arange(width - 1)
            m = np.take_along_axis(m, place + (place > at[:, None]), 1)
            if width == 2:
                out[rows, :1] = m
                break
            place = np.arange(width - 2)
            r = np.take_along_axis(r, place + (place >= at[:, None]), 1)
            before = np.flatnonzero(at > 0)
            r[before, at[before] - 1] = self.pairs.find(m[before, at[before] - 1], m[before, at[before]])
            after = np.flatnonzero(at < width - 2)
            r[after, at[after]] = self.pairs.find(m[after, at[after]], m[after, at[after] + 1])
        return out

    def merge_long(self, word: bytes) -> list[int]:
        ids = self.byte_id[np.frombuffer(word, np.uint8)].tolist()
        n = len(ids)
        after, before = [*range(1, n), -1], [-1, *range(n - 1)]
        rank = self.pairs.find(np.array(ids[:-1], np.int32), np.array(ids[1:], np.int32)).tolist()
        heap = [(r, i) for i, r in enumerate(rank) if r != NONE]
        rank.append(int(NONE))
        heapq.heapify(heap)
        bytes_of, ranks = self.token_bytes, self.ranks
        while heap:
            r, i = heapq.heappop(heap)
            if rank[i] != r:
                continue
            j = after[i]
            ids[i], rank[j] = r, -1
            k = after[i] = after[j]
            if k >= 0:
                before[k] = i
            for p in (before[i], i):
                if p >= 0:
                    q = after[p]
                    rank[p] = ranks.get(bytes_of[ids[p]] + bytes_of[ids[q]], int(NONE)) if q >= 0 else int(NONE)
                    if rank[p] != NONE:
                        heapq.heappush(heap, (rank[p], p))
        out, i = [], 0
        while i >= 0:
            out.append(ids[i])
            i = after[i]
        return out

    def encode_words(self, words: list[str]) -> list[bytes]:
        """Little-endian unsigned 32-bit ids of each word."""
        out: list[bytes] = [b""] * len(words)
        buckets: dict[int, list[int]] = {}
        raw = [w.encode("utf-8", "surrogatepass") for w in words]
        for i, w in enumerate(raw):
            whole = self.ranks.get(w)
            if whole is not None:
                out[i] = whole.to_bytes(4, "little")
            elif len(w) > LONG:
                out[i] = np.array(self.merge_long(w), "<u4").tobytes()
            elif w:
                n = len(w)
                buckets.setdefault(n if n <= 8 else (n + 3) // 4 * 4 if n <= 32 else 1 << (n - 1).bit_length(), []).append(i)
        for width, members in buckets.items():
            for at in range(0, len(members), 1 + 400_000 // width):
                part = members[at : at + 1 + 400_000 // width]
                m = np.full((len(part), width), -1, np.int32)
                joined = self.byte_id[np.frombuffer(b"".join([raw[i] for i in part]), np.uint8)]
                lengths = np.array([len(raw[i]) for i in part])
                m[np.arange(width) < lengths[:, None]] = joined
                done = self.merge_matrix(m)
                count = (done >= 0).sum(1)
                flat = done[done >= 0].astype("<u4").tobytes()
                ends = (4 * np.cumsum(count)).tolist()
                for i, a, b in zip(part, [0, *ends[:-1]], ends, strict=True):
                    out[i] = flat[a:b]
        return out

    def _learn(self, texts: list[str]) -> None:
        """Ids of new chunks, by way of their words."""
        split = [self.split.findall(t) for t in texts]
        new = sorted({w for ws in split for w in ws if w not in self.words})
        self.words.update(zip(new, self.encode_words(new), strict=True))
        words = self.words
        for t, ws in zip(texts, split, strict=True):
            self.chunks[t] = b"".join([words[w] for w in ws])

    def encode_batch(self, texts: list[str]) -> list[bytes]:
        """Ids of whole texts.  A text is cut where no match of the pattern can cross: before a single
        space and at a single line feed between other characters; else it is one chunk."""
        if len(self.words) > MEMO_ENTRIES:
            self.words = {}
        if len(self.chunks) > MEMO_ENTRIES:
            self.chunks = {}
        cut = [self._chunks(t) for t in texts]
        seen: set[str] = set()
        for c in cut:
            seen.update(c)
        self._learn([c for c in seen if c not in self.chunks])
        out = [b"".join(map(self.chunks.__getitem__, c)) for c in cut]
        for c in cut:
            if len(c) == 1 and len(c[0]) > 200:
                self.chunks.pop(c[0], None)  # whole texts are not worth keeping
        return out

    @staticmethod
    def _chunks(text: str) -> list[str]:
        if not text or ODD_SPACE.search(text):
            return [text]
        out: list[str] = []
        for line in text.split("\n"):
            first, *rest = line.split(" ")
            out += ["\n", first]
            out += [" " + p for p in rest]
        return out[1:]

    def decode(self, ids: np.ndarray) -> bytes:
        return b"".join(map(self.token_bytes.__getitem__, ids.tolist()))


@cache
def vocabulary(path: str, pattern: str) -> Vocabulary:
    return Vocabulary(read_ranks(None, path), pattern)


common.keeps_memo(vocabulary.cache_clear)

def _encode(texts: list[str], path: str, pattern: str) -> list[list[np.ndarray]]:
    v = vocabulary(path, pattern)
    return [[np.frombuffer(x, "<u4").astype(np.int32) for x in v.encode_batch(texts)]]


def encode(docs: DataFrame, path: str, pattern: str, text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """Append ``ids`` (array<int>)."""
    return common.with_text_columns(docs, text_col, partial(_encode, path=path, pattern=pattern), [("ids", T.ArrayType(T.IntegerType()))], keep)


def _round_trip(texts: list[str], path: str, pattern: str) -> list[list]:
    v = vocabulary(path, pattern)
    n, ids_sha, text_sha = [], [], []
    for at in range(0, len(texts), 512):
        for data in v.encode_batch(texts[at : at + 512]):
            n.append(len(data) // 4)
            ids_sha.append(hashlib.sha256(data).hexdigest())
            text_sha.append(hashlib.sha256(v.decode(np.frombuffer(data, "<u4"))).hexdigest())
    return [n, ids_sha, text_sha]


def digest(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """Number and digest of the ids, and digest of the bytes they decode to."""
    fields = [("n_tokens", T.LongType()), ("ids_sha256", T.StringType()), ("decoded_sha256", T.StringType())]
    return common.with_text_columns(docs, "text", partial(_round_trip, path=path, pattern=pattern), fields, keep=["doc_id"])
