"""Best-fit packing by the sum of squares of open bins per residual gap.

A document is its token ids and one closing id.  Only longer ones than a sequence are cut, into
full pieces; the first piece takes the rest, so every other piece fills a sequence by itself.
The remaining pieces go to bins: of all gaps that hold the piece, and a new bin, the choice is
the one after which the squared counts of open bins per residual gap sum to least.

At scale a shard of ``shard_pieces`` pieces (drawn by hash, so all shards look alike) is packed by
itself.  Within a shard pieces are taken from the longest down, in which order the rule leaves few
open bins; the shard's last open bins are all that sharding can waste.

Defined results: a null or empty text is the closing id alone; repeated rows are packed as often as
they occur; the empty table gives no rows.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator
from functools import cache, partial
from itertools import compress, repeat
from operator import is_

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F, types as T

from polyedge.llm import common

#: Bytes that the memos of a worker may hold: of chunks and their ids, half of it young, and of the pieces of whole texts.
MEMO_BYTES, KNOWN_BYTES = 96 << 20, 24 << 20
ENTRY = 180  # bytes of the objects of one entry besides its contents
LONGEST = 200  # longer chunks are not worth keeping
BATCH = 1024
# fixed values: white space other than the space and the line feed
OTHER_SPACE = "\t\r\x0b\x0c\x1c\x1d\x1e\x1f\x85\xa0\u1680\u2000\u2001\u2002\u2003\u2004\u2005\u2006\u2007\u2008\u2009\u200a\u2028\u2029\u202f\u205f\u3000"


@cache
def _tokenizer(path: str):
    from tokenizers import Tokenizer

    return Tokenizer.from_file(path)


def _chunks(text: str, special: list[str]) -> list[str] | None:
    """The text, a line feed put before it, cut before each line feed and at each space, which goes.

    So a chunk that does not start with a line feed follows a space.  No match of the tokenizer's
    split pattern crosses such a cut if it stands between two other characters, so the chunks
    encode alone.  None if the text holds white space of any other kind or arrangement, or a string
    that the tokenizer takes for a token of its own.
    """
    parts = f"\n{text}".replace("\n", " \n").split(" ")
    del parts[0]
    if "" in parts or "\n" in parts or any(c in text for c in OTHER_SPACE) or any(c in text for c in special):
        return None
    return parts


class DocumentEncoder:
    """Ids of whole texts as little-endian unsigned 32-bit bytes; chunks met before are looked up.

    New chunks go to the tokenizer as one joined text.  Each begins with a space or a line feed and
    holds no other, so a token that begins so marks where to cut the ids.
    Letters and the marks after them never share a token, so a known word with other marks is known.
    """

    MARKS = ".,!?;:*$%&#"

    def __init__(self, path: str):
        self.tokenizer = _tokenizer(path)
        self.special = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.line = len(self._encode("\n").tobytes())
        self.memo: dict[str, bytes] = {}
        self.held = 0  # bytes in the memo
        self.old: dict[str, bytes] = {}  # the memo before; what is met again comes back from it
        self.marks: dict[str, bytes] = {}
        self.known: dict[tuple[int, int], dict[bytes, list[tuple]]] = {}  # pieces of texts met before
        self.known_held = 0
        vocab = self.tokenizer.get_vocab(with_added_tokens=True)
        self.opens = np.zeros(max(vocab.values()) + 1, bool)
        self.opens[[i for t, i in vocab.items() if t[0] in "\u0120\u010a"]] = True  # a space and a line feed, as byte-level vocabularies write them

    def _encode(self, text: str) -> np.ndarray:
        return np.array(self.tokenizer.encode_batch_fast([text], add_special_tokens=False)[0].ids, "<u4")

    def _learn(self, new: list[str]) -> None:
        for at in range(0, len(new), 5000):
            part = new[at : at + 5000]
            ids = self._encode("".join([c if c[0] == "\n" else " " + c for c in part]))
            cuts = np.flatnonzero(self.opens[ids]).tolist()
            if len(cuts) != len(part):
                raise RuntimeError("a chunk did not start a token of its own")
            data = ids.tobytes()
            cuts = [4 * c for c in cuts]
            self.memo.update(zip(part, map(data.__getitem__, map(slice, cuts, [*cuts[1:], len(data)])), strict=True))

    def _add(self, missing: list[str]) -> None:
        memo, old, marks = self.memo, self.old, self.marks
        words, ends, plain = [], [], set()
        for c in missing:
            w = c.rstrip(self.MARKS)
            if len(w) < len(c) and w[-1:].isalpha():
                words.append(w)
                ends.append(c[len(w) :])
                if w not in memo:
                    if w in old:
                        memo[w] = old[w]
                    else:
                        plain.add(w)
            else:
                words.append(c)
                ends.append("")
                plain.add(c)
        self._learn(list(plain))
        if len(marks) > 10_000:
            marks.clear()
        for e in set(ends):
            if e not in marks:
                marks[e] = self._encode(e).tobytes() if e else b""
        for c, w, e in zip(missing, words, ends, strict=True):
            if e:
                memo[c] = memo[w] + marks[e]

    def __call__(self, texts: list[str]) -> list[bytes]:
        if self.held > MEMO_BYTES // 2:
            self.memo, self.old, self.held = {}, self.memo, 0
        memo, old = self.memo, self.old
        cut = [_chunks(t, self.special) for t in texts]
        found = [list(map(memo.get, c)) if c else [] for c in cut]
        missing: set[str] = set()
        for c, ids in zip(cut, found, strict=True):
            if c:
                missing.update(compress(c, map(is_, ids, repeat(None))))
        before = len(memo)
        if old:
            memo.update({c: old[c] for c in missing if c in old})
        self._add([c for c in missing if c not in memo] if old else list(missing))
        out = []
        for text, c, ids in zip(texts, cut, found, strict=True):
            if c is None:
                out.append(self._encode(text).tobytes())
            else:
                out.append(b"".join([memo[x] if y is None else y for x, y in zip(c, ids, strict=True)])[self.line :])
        for c in missing:
            if len(c) > LONGEST:
                memo.pop(c, None)
                memo.pop(c.rstrip(self.MARKS), None)
            else:
                self.held += len(c) + len(memo.get(c, b""))
        self.held += ENTRY * max(0, len(memo) - before)
        return out


def cut_lengths(n: int, capacity: int) -> list[tuple[int, int]]:
    """(start, length) of the pieces of ``n`` ids; the first takes the rest."""
    first = (n - 1) % capacity + 1
    return [(0, first)] + [(s, capacity) for s in range(first, n, capacity)]


@cache
def encoder(path: str) -> DocumentEncoder:
    return DocumentEncoder(path)


common.keeps_memo(encoder.cache_clear)

def _cut_documents(encode: DocumentEncoder, texts: list[str], capacity: int, end: bytes, with_ids: bool, known: dict[bytes, list[tuple]]) -> list[list[tuple]]:
    """(start, length, crc, ids) of the pieces of each text; a text met before by this worker is known."""
    if with_ids:
        keys: list[bytes] = [i.to_bytes(8, "little") for i in range(len(texts))]
        known = {}
    else:
        keys = [hashlib.blake2b(t.encode("utf-8", "surrogatepass"), digest_size=16).digest() for t in texts]
        if encode.known_held > KNOWN_BYTES:
            known.clear()
            encode.known_held = 0
    new = {k: t for k, t in zip(keys, texts, strict=True) if k not in known}
    for k, doc in zip(new, encode(list(new.values())), strict=True):
        doc += end
        parts = [(s, n, doc[4 * s : 4 * (s + n)]) for s, n in cut_lengths(len(doc) // 4, capacity)]
        known[k] = [(s, n, zlib.crc32(x), np.frombuffer(x, "<u4").astype(np.int32) if with_ids else None) for s, n, x in parts]
        encode.known_held += 0 if with_ids else ENTRY * (1 + len(parts))
    return [known[k] for k in keys]


def _pieces(batches: Iterator[pa.RecordBatch], path: str, capacity: int, closing_id: int, with_ids: bool) -> Iterator[pa.RecordBatch]:
    common.begin(__name__)
    encode, end = encoder(path), np.array([closing_id], "<u4").tobytes()
    known = encode.known.setdefault((capacity, closing_id), {})
    for b in batches:
        ids = b.column(0)
        for at in range(0, b.num_rows, BATCH):
            texts = [t or "" for t in b.column(1).slice(at, BATCH).to_pylist()]
            row, piece, start, length, crc, data = [], [], [], [], [], []
            for k, parts in enumerate(_cut_documents(encode, texts, capacity, end, with_ids, known)):
                for p, (s, n, c, x) in enumerate(parts):
                    row.append(at + k)
                    piece.append(p)
                    start.append(s)
                    length.append(n)
                    crc.append(c)
                    data.append(x)
            cols = [ids.take(pa.array(row, pa.int64())), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64())]
            names = ["doc_id", "piece", "start", "length", "ids_crc32"]
            if with_ids:
                cols.append(pa.array(data, pa.list_(pa.int32())))
                names.append("ids")
            yield pa.RecordBatch.from_arrays(cols, names=names)
    common.trim()


def pieces(docs: DataFrame, tokenizer_path: str, capacity: int = 2048, closing_id: int = 0, with_ids: bool = False) -> DataFrame:
    """One row per piece: doc_id, piece, start, length, ids_crc32 and, if asked, ids."""
    common.ship(docs.sparkSession)
    kind = docs.schema["doc_id"].dataType
    fields = [T.StructField("doc_id", kind), T.StructField("piece", T.IntegerType()), T.StructField("start", T.LongType()), T.StructField("length", T.LongType()), T.StructField("ids_crc32", T.LongType())]
    if with_ids:
        fields.append(T.StructField("ids", T.ArrayType(T.IntegerType())))
    run = partial(_pieces, path=tokenizer_path, capacity=capacity, closing_id=closing_id, with_ids=with_ids)
    return docs.select("doc_id", F.col("text").cast("string")).mapInArrow(run, T.StructType(fields))


def sum_of_squares(sizes: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray]:
    """Bin and offset of each size, taken in the order given."""
    count = np.zeros(capacity + 1, np.int64)  # open bins per residual gap; 0 and capacity stay empty
    open_bins: list[list[int]] = [[] for _ in range(capacity + 1)]
    gap_of: list[int] = []
    where, offset = np.empty(len(sizes), np.int64), np.empty(len(sizes), np.int64)
    for i, s in enumerate(sizes.tolist()):
        chosen = -1
        if s < capacity:
            # change of the sum: N(g) falls by one, N(g - s) rises by one; a filled bin is not open
            before = count[s:capacity]
            delta = np.where(before > 0, 2 * (count[: capacity - s] - before) + 2, np.iinfo(np.int64).max)
            delta[0] = 1 - 2 * before[0] if before[0] else delta[0]
            k = int(delta.argmin())
            if before[k] and delta[k] <= 2 * count[capacity - s] + 1:
                chosen = k + s
        if chosen < 0:
            where[i], offset[i] = len(gap_of), 0
            gap_of.append(capacity - s)
            b, gap = len(gap_of) - 1, capacity - s
        else:
            b = open_bins[chosen].pop()
            count[chosen] -= 1
            where[i], offset[i] = b, capacity - chosen
            gap = chosen - s
        if gap:
            open_bins[gap].append(b)
            count[gap] += 1
    return where, offset


def _pack_shard(rows: pd.DataFrame, capacity: int) -> pd.DataFrame:
    rows = rows.sort_values(["length", "ids_crc32", "doc_id", "piece"], ascending=[False, True, True, True], kind="stable")
    where, offset = sum_of_squares(rows["length"].to_numpy(), capacity)
    return rows.assign(sequence_id=rows["__shard"].astype("int64") * (1 << 32) + where, offset=offset).drop(columns="__shard")


def pack(piece_rows: DataFrame, capacity: int = 2048, shard_pieces: int = 50_000) -> DataFrame:
    """Append sequence_id and offset to the rows of ``pieces``.

    Shards are drawn by a hash of the piece, sized from the number of pieces, so each task holds a
    bounded number of rows whatever the skew of the input.
    """
    rows = common.cut(piece_rows)
    shards = max(1, -(-rows.count() // shard_pieces))
    salted = rows.withColumn("__shard", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32", F.monotonically_increasing_id()), F.lit(shards)).cast("int"))
    schema = T.StructType([*rows.schema.fields, T.StructField("sequence_id", T.LongType()), T.StructField("offset", T.LongType())])
    return salted.groupBy("__shard").applyInPandas(_packer(capacity), schema)


def _packer(capacity: int):
    def pack_shard(rows: pd.DataFrame) -> pd.DataFrame:
        return _pack_shard(rows, capacity)

    return pack_shard


def sequences(packed: DataFrame) -> DataFrame:
    """Token ids per sequence from packed pieces with ``ids``: (sequence_id, ids, doc_starts)."""
    held = packed.groupBy("sequence_id").agg(F.sort_array(F.collect_list(F.struct("offset", "ids"))).alias("parts"))
    return held.select("sequence_id", F.flatten(F.transform("parts", lambda p: p["ids"])).alias("ids"), F.transform("parts", lambda p: p["offset"]).alias("doc_starts"))
