"""Chat formatting by token-level assembly.

Every turn is a header segment, its text and a closing segment.  Segments are encoded separately;
control strings are never encoded: their reserved ids, above the vocabulary, are spliced between
segments, so no text can produce one.  Lengths of the segments give the token offsets and the loss
mask by prefix sums.  A control string inside a role or a text is escaped by a backslash behind its
first character (one more if some stand there already), which unescaping takes out again, so the
formatted string can be parsed too.

Template of a turn: ``<|turn|>`` role ``<|text|>`` text ``<|end|>``; a conversation starts with
``<|chat|>`` and closes with ``<|done|>``.  Loss falls on texts of the assistant only.

Defined results: null texts and roles are empty; a null conversation id is a conversation of its
own; turns of one number follow by role, then by their ids; repeated rows are repeated turns.  The turns of
one conversation stream through one task in order (digests are sequential) and are never held
together; encoding happens before, row by row, on all tasks.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from functools import cache, partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F, types as T

from polyedge.llm import bpe, common

# fixed values: control strings of the template, then those of common chat templates
TEMPLATE = ["<|chat|>", "<|turn|>", "<|text|>", "<|end|>", "<|done|>"]
FOREIGN = ["<s>", "</s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>", "<|im_start|>", "<|im_end|>", "<|endoftext|>"]

_rest = "|".join(sorted((re.escape(c[1:]) for c in TEMPLATE + FOREIGN), key=len, reverse=True))
TO_ESCAPE = re.compile(rf"([<\[])(\\*)(?=(?:{_rest}))")
ESCAPED = re.compile(rf"([<\[])\\(\\*)(?=(?:{_rest}))")


def escape(text: str) -> str:
    return TO_ESCAPE.sub(r"\1\\\2", text) if "<" in text or "[" in text else text


def unescape(text: str) -> str:
    return ESCAPED.sub(r"\1\2", text) if "\\" in text else text


class Assembler:
    """Turns to ids and back, over a byte-level vocabulary with the reserved ids above it."""

    def __init__(self, path: str, pattern: str):
        self.vocab = bpe.vocabulary(path, pattern)
        self.base = len(self.vocab.token_bytes)
        self.reserved = {c: self.base + i for i, c in enumerate(TEMPLATE)}
        # bytes that do not continue a character, of each token and each reserved id
        lengths = [len(t) for t in self.vocab.token_bytes] + [len(c) for c in TEMPLATE]
        starts = np.frombuffer(b"".join(self.vocab.token_bytes) + "".join(TEMPLATE).encode(), np.uint8) & 0xC0 != 0x80
        self.n_chars = np.diff(np.concatenate([[0], np.cumsum(starts)])[np.concatenate([[0], np.cumsum(lengths)])])

    def turns(self, roles: list[str], texts: list[str]) -> list[tuple[np.ndarray, int, int]]:
        """Ids of each turn with the first and the end token of its text, from prefix sums."""
        turn, text, end = (self.reserved[c] for c in ("<|turn|>", "<|text|>", "<|end|>"))
        heads = self.vocab.encode_batch([escape(r) for r in roles])
        bodies = self.vocab.encode_batch([escape(t) for t in texts])
        out = []
        for h, b in zip(heads, bodies, strict=True):
            segments = [[turn], np.frombuffer(h, "<u4"), [text], np.frombuffer(b, "<u4"), [end]]
            ends = np.cumsum([len(s) for s in segments])
            out.append((np.concatenate(segments).astype(np.int32), int(ends[2]), int(ends[3])))
        return out

    def to_string(self, ids: np.ndarray) -> str:
        parts = [TEMPLATE[i - self.base].encode() if i >= self.base else self.vocab.token_bytes[i] for i in ids.tolist()]
        return b"".join(parts).decode("utf-8", "surrogatepass")

    def read(self, ids: np.ndarray) -> list[tuple[str, str, int, int]]:
        """Role and text, unescaped, of every turn in ``ids``, and where its text stands."""
        turn, middle, end = (self.reserved[c] for c in ("<|turn|>", "<|text|>", "<|end|>"))
        at = np.flatnonzero(ids >= self.base).tolist()
        kind = ids[at].tolist()
        out = []
        for i, k in enumerate(kind):
            if k == turn:
                if kind[i + 1 : i + 3] != [middle, end]:
                    raise ValueError("a turn is not complete")
                a, m, e = at[i : i + 3]
                role, text = (unescape(self.vocab.decode(x).decode("utf-8", "surrogatepass")) for x in (ids[a + 1 : m], ids[m + 1 : e]))
                out.append((role, text, m + 1, e))
        return out

    def parse(self, ids: np.ndarray) -> list[tuple[str, str]]:
        """Role and text of every turn in ``ids``, unescaped."""
        return [r[:2] for r in self.read(ids)]


@cache
def assembler(path: str, pattern: str) -> Assembler:
    return Assembler(path, pattern)


def _turn_rows(batches: Iterator[pa.RecordBatch], path: str, pattern: str) -> Iterator[pa.RecordBatch]:
    made = assembler(path, pattern)
    for b in batches:
        for at in range(0, b.num_rows, 1000):
            p = b.slice(at, 1000)
            roles = [x or "" for x in p.column(2).to_pylist()]
            texts = [x or "" for x in p.column(3).to_pylist()]
            got = made.turns(roles, texts)
            loss = [r == "assistant" for r in roles]
            cols = [
                p.column(0),
                p.column(1),
                pa.array([g[0] for g in got], pa.list_(pa.int32())),
                pa.array([g[1] if y else 0 for g, y in zip(got, loss, strict=True)], pa.int32()),
                pa.array([g[2] if y else 0 for g, y in zip(got, loss, strict=True)], pa.int32()),
                p.column(2),
            ]
            yield pa.RecordBatch.from_arrays(cols, names=["conv_id", "turn", "ids", "loss_start", "loss_end", "role"])


def format_turns(conversations: DataFrame, path: str, pattern: str) -> DataFrame:
    """One row per turn: ids of the formatted turn and the token range under the loss mask."""
    common.ship(conversations.sparkSession)
    c = conversations.select("conv_id", "turn", F.col("role").cast("string"), F.col("text").cast("string"))
    schema = T.StructType([c.schema["conv_id"], c.schema["turn"], T.StructField("ids", T.ArrayType(T.IntegerType())), T.StructField("loss_start", T.IntegerType()), T.StructField("loss_end", T.IntegerType()), T.StructField("role", T.StringType())])
    return c.mapInArrow(partial(_turn_rows, path=path, pattern=pattern), schema)


def in_order(turns: DataFrame) -> DataFrame:
    """Turns of a conversation next to each other and in order, in one partition each."""
    return turns.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "ids")


def assemble(turns: DataFrame, path: str, pattern: str) -> DataFrame:
    """One row per conversation: ``ids``, ``loss`` (0/1 per token) and the formatted ``text``.

    A row holds its whole conversation; for ones too long for a row use ``in_order``.
    """
    kind = turns.schema["conv_id"].dataType
    schema = T.StructType([T.StructField("conv_id", kind), T.StructField("ids", T.ArrayType(T.IntegerType())), T.StructField("loss", T.ArrayType(T.ByteType())), T.StructField("text", T.StringType())])
    return in_order(turns).mapInArrow(partial(_conversations, path=path, pattern=pattern), schema)


def _grouped(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[bool, object, np.ndarray, int, int]]:
    """(starts a conversation, id, ids, loss range) of each turn in order."""
    last: object = ...
    for b in batches:
        conv, lo, hi = b.column(0).to_pylist(), b.column(3).to_pylist(), b.column(4).to_pylist()
        flat, ends = b.column(2).values.to_numpy(zero_copy_only=False), b.column(2).offsets.to_pylist()
        for i, c in enumerate(conv):
            yield c != last or last is ..., c, flat[ends[i] : ends[i + 1]], lo[i], hi[i]
            last = c


def _conversations(batches: Iterator[pa.RecordBatch], path: str, pattern: str) -> Iterator[pa.RecordBatch]:
    made = assembler(path, pattern)
    names = ["conv_id", "ids", "loss", "text"]
    held: list = []

    def row(conv: object) -> pa.RecordBatch:
        ids = np.concatenate([[made.reserved["<|chat|>"]], *[h[0] for h in held], [made.reserved["<|done|>"]]]).astype(np.int32)
        begins = np.cumsum([1, *[len(h[0]) for h in held]])
        edges = np.zeros(len(ids) + 1, np.int32)
        for b, (_, lo, hi) in zip(begins, held, strict=False):
            edges[b + lo] += 1
            edges[b + hi] -= 1
        loss = np.cumsum(edges[:-1]).astype(np.int8)
        return pa.RecordBatch.from_arrays([pa.array([conv], kind), pa.array([ids]), pa.array([loss]), pa.array([made.to_string(ids)])], names=names)

    conv, kind = None, None
    for b in batches:
        kind = b.schema.field(0).type
        for start, c, ids, lo, hi in _grouped(iter([b])):
            if held and c != conv or (start and not held):
                if held:
                    yield row(conv)
                held, conv = [], c
            held.append((ids, lo, hi))
    if held:
        yield row(conv)


def _digests(batches: Iterator[pa.RecordBatch], path: str, pattern: str) -> Iterator[pa.RecordBatch]:
    made = assembler(path, pattern)
    frame = len(TEMPLATE[0]) + len(TEMPLATE[4])
    rows: list[list] = []
    kind = pa.int64()
    open_conv: list | None = None  # id, turns, digest, loss characters, loss digest, characters

    def close() -> None:
        if open_conv is not None:
            rows.append([open_conv[0], open_conv[1], open_conv[2].hexdigest(), open_conv[3], open_conv[4].hexdigest(), open_conv[5]])

    def batch() -> pa.RecordBatch:
        cols = list(zip(*rows, strict=True)) or [[]] * 6
        kinds = [kind, pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64()]
        return pa.RecordBatch.from_arrays([pa.array(list(c), k) for c, k in zip(cols, kinds, strict=True)], names=["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"])

    for b in batches:
        kind = b.schema.field(0).type
        for _, conv, ids, lo, hi in _grouped(iter([b])):
            if open_conv is None or open_conv[0] != conv:
                close()
                open_conv = [conv, 0, hashlib.sha256(), 0, hashlib.sha256(), frame]
            read = made.read(ids)
            for role, text, _, _ in read:
                open_conv[1] += 1
                open_conv[2].update(f"{role}\n{text}\n".encode("utf-8", "surrogatepass"))
            if lo < hi:
                same = [text for _, text, a, e in read if (a, e) == (lo, hi)]  # the mask covers a text: read once
                loss = same[0] if same else unescape(made.to_string(ids[lo:hi]))
                open_conv[3] += len(loss)
                open_conv[4].update(loss.encode("utf-8", "surrogatepass"))
            open_conv[5] += int(made.n_chars[ids].sum())
        if len(rows) >= 1000:
            yield batch()
            rows = []
    close()
    yield batch()


def digest(turns: DataFrame, path: str, pattern: str) -> DataFrame:
    """The contract's columns, read back from the ids and masks of ``format_turns``."""
    schema = T.StructType([T.StructField("conv_id", turns.schema["conv_id"].dataType), T.StructField("n_turns", T.LongType()), T.StructField("turns_sha256", T.StringType()), T.StructField("loss_chars", T.LongType()), T.StructField("loss_sha256", T.StringType()), T.StructField("formatted_chars", T.LongType())])
    return in_order(turns).mapInArrow(partial(_digests, path=path, pattern=pattern), schema)
