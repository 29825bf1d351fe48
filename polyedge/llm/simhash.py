"""SimHash near-duplicates found by anchor points of a covering code.

Anchors are the words of a product code over the 64 bits: two perfect binary Golay codes (23 bits,
covering radius 3), one Hamming code (15 bits, radius 1) and one repetition code (3 bits, radius 1).
For two fingerprints at most two bits apart some point is within one bit of both; the anchor that
covers this point is, in each block, within the covering radius of it.  So each fingerprint goes to
every anchor that lies within the covering radius in every block, plus one bit (half the threshold)
in one of them: about 17 anchors.  Fingerprints that share an anchor are compared there.

An anchor with more than ``cap`` fingerprints is not compared pairwise: its fingerprints move to
the finest covering code, of radius zero, whose anchors are all points.  There each goes to its own
point and its 64 neighbours; all that meet at one point are at most two bits apart, and at most 65
can meet, so the result is the same and no group is large.

Anchors only see distinct fingerprints, so copies cost nothing.  Links leave as stars (member to
smallest member), never as all pairs; components come from alternating large-star and small-star
rounds over checkpointed edges.

Defined results: a null or empty text, or one of white space only, has fingerprint zero and links
as any other; one or two words make a single shingle; repeated rows each get their result.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from functools import cache, partial
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, functions as F, types as T

from polyedge.llm import common

BITS = np.arange(64, dtype=np.uint64)


def fingerprint(text: str, words: int = 3, seed: int = 42) -> int:
    """Bitwise majority of the XXH64 of all word shingles of the ASCII-lower-cased text."""
    w = text.encode("utf-8", "surrogatepass").lower().split()
    if not w:
        return 0
    h = xxhash.xxh64_intdigest
    if len(w) <= words:
        a = [h(b" ".join(w), seed)]
    else:
        a = [h(b" ".join(t), seed) for t in zip(*(w[i:] for i in range(words)), strict=False)]
    total = np.zeros(64, np.int64)
    for i in range(0, len(a), 4096):
        x = np.array(a[i : i + 4096], dtype="<u8")
        total += np.unpackbits(x.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(((2 * total > len(a)).astype(np.uint64) << BITS).sum())


def _signed(x: list[int]) -> np.ndarray:
    return np.array(x, dtype=np.uint64).view(np.int64)


def _fingerprints(texts: list[str], words: int) -> list[np.ndarray]:
    return [_signed([fingerprint(t, words) for t in texts])]


@dataclass(frozen=True)
class Block:
    """A perfect code on ``n`` bits from bit ``at`` on; arrays are indexed by the syndrome."""

    at: int
    n: int
    bit_syndrome: np.ndarray
    leader: np.ndarray  # error of weight <= radius
    beyond: np.ndarray  # (syndromes, most) errors of weight radius + 1
    n_beyond: np.ndarray

    def syndrome(self, y: np.ndarray) -> np.ndarray:
        s = np.zeros(len(y), np.uint64)
        for i in range(self.n):
            s ^= ((y >> np.uint64(i)) & np.uint64(1)) * self.bit_syndrome[i]
        return s.astype(np.int64)


def _block(at: int, n: int, radius: int, bit_syndrome: list[int]) -> Block:
    size = 1 << max(s.bit_length() for s in bit_syndrome)
    leader, beyond = {}, {k: [] for k in range(size)}
    for weight in range(radius + 2):
        for on in combinations(range(n), weight):
            s = e = 0
            for i in on:
                s ^= bit_syndrome[i]
                e |= 1 << i
            if weight <= radius:
                leader[s] = e
            else:
                beyond[s].append(e)
    assert len(leader) == size, "not a perfect code"
    most = max(map(len, beyond.values()))
    table = np.zeros((size, most), np.uint64)
    for s, es in beyond.items():
        table[s, : len(es)] = es
    return Block(at, n, np.array(bit_syndrome, np.uint64), np.array([leader[s] for s in range(size)], np.uint64), table, np.array([len(beyond[s]) for s in range(size)]))


def _remainders(n: int, poly: int) -> list[int]:
    """Powers of x modulo a generator polynomial: the syndromes of single bits."""
    out, x, top = [], 1, 1 << (poly.bit_length() - 1)
    for _ in range(n):
        out.append(x)
        x <<= 1
        if x & top:
            x ^= poly
    return out


@cache
def anchor_code() -> tuple[Block, ...]:
    # fixed values: generator polynomials of the Golay code (23,12) and of the Hamming code (15,11)
    golay, hamming = 0b110001110101, 0b10011
    return (
        _block(0, 23, 3, _remainders(23, golay)),
        _block(23, 23, 3, _remainders(23, golay)),
        _block(46, 15, 1, _remainders(15, hamming)),
        _block(61, 3, 1, [1, 2, 3]),
    )


def anchors(fps: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Index of the fingerprint and the anchor, for all anchors of ``fps`` (uint64)."""
    code = anchor_code()
    home = fps.copy()
    syn = []
    for b in code:
        y = (fps >> np.uint64(b.at)) & np.uint64((1 << b.n) - 1)
        s = b.syndrome(y)
        syn.append(s)
        home ^= b.leader[s] << np.uint64(b.at)
    which, where = [np.arange(len(fps))], [home]
    for b, s in zip(code, syn, strict=True):
        for k in range(b.beyond.shape[1]):
            on = np.flatnonzero(b.n_beyond[s] > k)
            if len(on):
                e = b.leader[s[on]] ^ b.beyond[s[on], k]
                which.append(on)
                where.append(home[on] ^ (e << np.uint64(b.at)))
    return np.concatenate(which), np.concatenate(where)


def _batch(names: list[str], *cols: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c.view(np.int64) if c.dtype == np.uint64 else c) for c in cols], names=names)


def _replicate(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        fps = b.column(0).to_numpy(zero_copy_only=False).view(np.uint64)
        for i in range(0, len(fps), 20_000):
            part = fps[i : i + 20_000]
            which, where = anchors(part)
            yield _batch(["anchor", "fp"], where, part[which])


def _points(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    flips = np.concatenate([np.zeros(1, np.uint64), np.uint64(1) << BITS])
    for b in batches:
        fps = b.column(0).to_numpy(zero_copy_only=False).view(np.uint64)
        for i in range(0, len(fps), 5_000):
            part = fps[i : i + 5_000]
            yield _batch(["anchor", "fp"], (part[:, None] ^ flips).ravel(), np.repeat(part, 65))


def stars(anchor: np.ndarray, fp: np.ndarray, threshold: int) -> tuple[np.ndarray, np.ndarray]:
    """Links between sorted rows of the same anchor, reduced to (member, smallest member)."""
    n = len(fp)
    at = np.arange(n)
    left, right = [], []
    lag = 1
    while len(at := at[at + lag < n]) and len(at := at[anchor[at] == anchor[at + lag]]):
        near = np.bitwise_count(fp[at] ^ fp[at + lag]) <= threshold
        left.append(at[near])
        right.append(at[near] + lag)
        lag += 1
    if not left or not sum(map(len, left)):
        return fp[:0], fp[:0]
    i, j = np.concatenate(left), np.concatenate(right)
    root = np.arange(n)
    while True:
        low = np.minimum(root[i], root[j])
        new = root.copy()
        np.minimum.at(new, i, low)
        np.minimum.at(new, j, low)
        new = new[new]
        if (new == root).all():
            break
        root = new
    on = np.flatnonzero(root != np.arange(n))
    return fp[on], fp[root[on]]


def _compare(batches: Iterator[pa.RecordBatch], threshold: int) -> Iterator[pa.RecordBatch]:
    """Rows come sorted by anchor; the last anchor of a batch waits for the next batch."""
    rest_a, rest_f = np.empty(0, np.int64), np.empty(0, np.uint64)
    for b in batches:
        a = np.concatenate([rest_a, b.column(0).to_numpy(zero_copy_only=False)])
        f = np.concatenate([rest_f, b.column(1).to_numpy(zero_copy_only=False).view(np.uint64)])
        cut = int(np.searchsorted(a, a[-1])) if len(a) else 0
        yield _batch(["a", "b"], *stars(a[:cut], f[:cut], threshold))
        rest_a, rest_f = a[cut:], f[cut:]
    yield _batch(["a", "b"], *stars(rest_a, rest_f, threshold))


def links(fps: DataFrame, threshold: int = 2, cap: int = 512) -> DataFrame:
    """Star links (a, b) that join exactly the fingerprints connected at ``threshold`` bits.

    ``fps`` has one column ``fp`` (long) of distinct values.  Thresholds up to 2 are supported.
    """
    if threshold not in (0, 1, 2):
        raise ValueError("anchors replicate for thresholds of at most two bits")
    common.ship(fps.sparkSession)
    replicas = fps.mapInArrow(partial(common.tidied, run=_replicate), "anchor long, fp long")
    hot = common.cut(replicas.groupBy("anchor").count().where(F.col("count") > cap).select("anchor"))
    if hot.isEmpty():
        cold, fine = replicas, None
    else:
        cold = replicas.join(hot, "anchor", "left_anti")
        moved = replicas.join(hot, "anchor", "left_semi").select("fp").distinct()
        met = moved.mapInArrow(partial(common.tidied, run=_points), "anchor long, fp long").groupBy("anchor").agg(F.collect_set("fp").alias("fps"))
        fine = met.where(F.size("fps") > 1).select(F.explode("fps").alias("a"), F.array_min("fps").alias("b"))
        if threshold < 2:  # points join fingerprints two bits apart
            fine = met.select(F.explode("fps").alias("a"), "anchor").select("a", F.col("anchor").alias("b")).join(moved.select(F.col("fp").alias("b")), "b", "left_semi") if threshold else fine.limit(0)
    near = cold.repartition("anchor").sortWithinPartitions("anchor", "fp").mapInArrow(partial(common.tidied, run=partial(_compare, threshold=threshold)), "a long, b long")
    return near if fine is None else near.unionByName(fine.select("a", "b"))


def _settled(e: DataFrame) -> bool:
    """Whether every node points to one root that points to none."""
    ends = e.select(F.col("u").alias("x"), F.lit(1).alias("up"), F.lit(0).alias("down")).unionByName(e.select(F.col("v").alias("x"), F.lit(0).alias("up"), F.lit(1).alias("down")))
    return ends.groupBy("x").agg(F.sum("up").alias("up"), F.max("down").alias("down")).where("up > 1 OR up > 0 AND down > 0").isEmpty()


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, root) for every node of ``edges`` (a, b), by alternating large and small stars."""
    e = common.cut(edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    for _ in range(max_rounds):
        if _settled(e):
            break
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.when(F.col("v") == F.col("m"), F.col("u")).otherwise(F.col("v")).alias("u"), F.col("m").alias("v"))
        e = common.cut(small.where("u <> v").distinct())
        common.tidy(e.sparkSession)
    else:
        raise RuntimeError("components did not settle")
    return e.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(e.select(F.col("v").alias("node"), F.col("v").alias("root"))).distinct()


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 3, threshold: int = 2, cap: int = 512) -> DataFrame:
    """One row per document: id, ``fp`` (long) and ``component_id``, the smallest id reachable."""
    rows = common.cut(common.with_text_columns(docs, text_col, partial(_fingerprints, words=words), [("fp", T.LongType())], keep=[id_col]))
    smallest = rows.groupBy("fp").agg(F.min(id_col).alias("__low"))
    found = components(links(smallest.select("fp"), threshold, cap))
    marked = smallest.join(found, smallest.fp == found.node, "left").select("fp", "__low", F.coalesce("root", "fp").alias("root"))
    low = marked.groupBy("root").agg(F.min("__low").alias("component_id"))
    classes = marked.join(low, "root").select("fp", "component_id")
    return rows.join(classes, "fp").select(id_col, "fp", "component_id")


# ---------------------------------------------------------------- similarity of 0.8 and more

FREQUENT, MOST_FREQUENT, CELL, MARKS, SHARES = 16, 200_000, 512, 8, 32
SPREAD = np.uint64(0x9E3779B97F4A7C15)


def normal_words(text: str) -> list[bytes]:
    return text.encode("utf-8", "surrogatepass").lower().split()


def shingle_set(words: list[bytes], k: int) -> set[bytes]:
    if not words:
        return set()
    return {b" ".join(words[i : i + k]) for i in range(max(1, len(words) - k + 1))}


def similarity(a: str, b: str, k: int = 5) -> float:
    """Jaccard similarity of the word shingle sets; two texts without words are alike."""
    x, y = shingle_set(normal_words(a), k), shingle_set(normal_words(b), k)
    return len(x & y) / len(x | y) if x or y else 1.0


def shingle_keys(words: list[bytes], k: int) -> np.ndarray:
    """Sorted 64-bit hashes of the shingle set."""
    if not words:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(xxhash.xxh64_intdigest, words), np.uint64, len(words))
    n = max(1, len(h) - k + 1)
    x = np.zeros(n, np.uint64)
    for i in range(min(k, len(h))):
        x = x * SPREAD + h[i : i + n]
        x ^= x >> np.uint64(29)
    return np.unique(x * SPREAD)


@dataclass(frozen=True)
class Frequent:
    """Keys that many documents hold (sorted) and how many: they come last in the order of keys."""

    keys: np.ndarray
    counts: np.ndarray

    def of(self, h: np.ndarray) -> np.ndarray:
        if not len(self.keys):
            return np.zeros(len(h), np.int64)
        at = np.minimum(np.searchsorted(self.keys, h), len(self.keys) - 1)
        return np.where(self.keys[at] == h, self.counts[at], 0)


NONE_FREQUENT = Frequent(np.empty(0, np.uint64), np.empty(0, np.int64))


def first_keys(h: np.ndarray, at_least: float, frequent: Frequent = NONE_FREQUENT) -> np.ndarray:
    """The first keys in one order of all keys, so many that two sets of similarity ``at_least`` share one.

    Such sets share at least ``at_least`` of the keys of either, so the first key that they share
    has no more than the others before it.
    """
    if not len(h):
        return h
    many = len(h) - math.ceil(at_least * len(h) - 1e-6) + 1
    return h[np.lexsort((h, frequent.of(h)))[:many]] if len(frequent.keys) else h[:many]


def _emit_first(batches: Iterator[pa.RecordBatch], words: int, at_least: float) -> Iterator[pa.RecordBatch]:
    for b in batches:
        for i in range(0, b.num_rows, 500):
            found = [first_keys(shingle_keys(normal_words(t or ""), words), at_least) for t in b.column(0).slice(i, 500).to_pylist()]
            yield _batch(["key"], np.concatenate(found))


def marks(h: np.ndarray) -> np.ndarray:
    """Parity of the number of keys at each of 512 places: two sets differ in at least as many keys as marks."""
    return np.packbits(np.bincount((h & np.uint64(64 * MARKS - 1)).astype(np.int64), minlength=64 * MARKS) & 1, bitorder="little").view(np.int64)


def frequent_keys(texts: DataFrame, words: int, at_least: float) -> Frequent:
    """The keys found first in the most texts.  They set the order of the keys, and with it the
    number of candidates, never which pairs are similar: so their number may be bounded."""
    common.ship(texts.sparkSession)
    seen = texts.mapInArrow(partial(common.tidied, run=partial(_emit_first, words=words, at_least=at_least)), "key long")
    top = seen.groupBy("key").count().where(F.col("count") > FREQUENT).orderBy(F.desc("count"), "key").limit(MOST_FREQUENT).toArrow()
    keys, counts = top.column(0).to_numpy().view(np.uint64), top.column(1).to_numpy()
    order = np.argsort(keys)
    return Frequent(keys[order], counts[order])


def _described(texts: list[str], words: int, at_least: float, frequent: Frequent) -> list[list]:
    digest, fp, n, mark, first = [], [], [], [], []
    for t in texts:
        w = normal_words(t)
        h = shingle_keys(w, words)
        digest.append(hashlib.blake2b(b" ".join(w), digest_size=16).hexdigest())
        fp.append(fingerprint(t, words))
        n.append(len(h))
        mark.append(marks(h))
        first.append(first_keys(h, at_least, frequent).view(np.int64))
    return [digest, _signed(fp), n, mark, first]


def _verified(batches: Iterator[pa.RecordBatch], words: int, at_least: float) -> Iterator[pa.RecordBatch]:
    """Rows come sorted by centre, its own text before the texts to compare with it."""
    centre, x = None, set()
    for b in batches:
        left, right = [], []
        for c, own, node, text in zip(*(b.column(i).to_pylist() for i in range(4)), strict=True):
            y = shingle_set(normal_words(text or ""), words)
            if own == 0:
                centre, x = c, y
                continue
            if c != centre:
                raise RuntimeError("a text to compare came without its centre")
            both = len(x & y)
            if both >= (at_least - 1e-12) * (len(x) + len(y) - both):
                left.append(c)
                right.append(node)
        yield _batch(["a", "b"], np.array(left, np.int64), np.array(right, np.int64))


def similar_pairs(pairs: DataFrame, texts: Callable[[DataFrame], DataFrame], words: int, at_least: float) -> DataFrame:
    """The pairs (a, b) whose texts have the similarity, compared exactly.

    ``texts`` gives (node, text) for a frame of nodes.
    The end of the lesser number is the centre of a pair.  A cell holds a centre's text and a share of
    its partners, by hash one of ``SHARES``; texts stream through it one at a time, so a text with very
    many partners is spread over tasks and one text travels for a pair.
    """
    pairs = common.cut(pairs.select(F.least("a", "b").alias("centre"), F.greatest("a", "b").alias("node")).distinct())
    common.tidy(pairs.sparkSession)
    dealt = pairs.withColumn("share", F.pmod(F.xxhash64("node"), F.lit(SHARES)))
    used = common.cut(texts(pairs.select(F.explode(F.array("centre", "node")).alias("node")).distinct()))
    own = dealt.select("centre", "share").distinct().join(used.select(F.col("node").alias("centre"), "text"), "centre").select("centre", F.lit(0).alias("own"), F.col("centre").alias("node"), "text", "share")
    partners = dealt.join(used, "node").select("centre", F.lit(1).alias("own"), "node", "text", "share")
    cells = own.unionByName(partners).repartition("centre", "share").sortWithinPartitions("centre", "share", "own")
    out = common.cut(cells.select("centre", "own", "node", "text").mapInArrow(partial(common.tidied, run=partial(_verified, words=words, at_least=at_least)), "a long, b long"))
    common.tidy(pairs.sparkSession)
    return out


def _cell_pairs(cell: np.ndarray, block: np.ndarray, inner: np.ndarray, node: np.ndarray, root: np.ndarray, n: np.ndarray, pos: np.ndarray, *mark: np.ndarray, at_least: float) -> tuple[np.ndarray, np.ndarray]:
    """Pairs of the same cell that may be similar and are not linked yet.

    Where the key is the first that both hold, they share no more than it and what follows it in
    either; the pair needs at_least/(1+at_least) of both sizes together, and differs in the rest.
    """
    at, lag, left, right = np.arange(len(cell)), 1, [], []
    need, mark = at_least / (1 + at_least), np.stack(mark, 1).view(np.uint64)
    while len(at := at[at + lag < len(cell)]) and len(at := at[cell[at] == cell[at + lag]]):
        to = at + lag
        on = (root[at] != root[to]) & ((inner[at] & inner[to]) | (block[at] != block[to]))
        on &= np.minimum(n[at], n[to]) >= at_least * np.maximum(n[at], n[to]) - 1e-6
        on &= np.minimum(n[at] - pos[at], n[to] - pos[to]) >= need * (n[at] + n[to]) - 1e-6
        a, b = at[on], to[on]
        on = np.bitwise_count(mark[a] ^ mark[b]).sum(1) <= (1 - 2 * need + 1e-12) * (n[a] + n[b])
        left.append(node[a[on]])
        right.append(node[b[on]])
        lag += 1
    if not left:
        return node[:0], node[:0]
    x, y = np.concatenate(left), np.concatenate(right)
    return np.minimum(x, y), np.maximum(x, y)


def _compare_cells(batches: Iterator[pa.RecordBatch], at_least: float) -> Iterator[pa.RecordBatch]:
    """Rows come sorted by cell; the last cell of a batch waits for the next batch."""
    rest = None
    for b in batches:
        new = [c.to_numpy(zero_copy_only=False) for c in b.columns]
        cols = new if rest is None else [np.concatenate(two) for two in zip(rest, new, strict=True)]
        cut = int(np.searchsorted(cols[0], cols[0][-1])) if len(cols[0]) else 0
        yield _batch(["a", "b"], *_cell_pairs(*(c[:cut] for c in cols), at_least=at_least))
        rest = [c[cut:] for c in cols]
    if rest is not None:
        yield _batch(["a", "b"], *_cell_pairs(*rest, at_least=at_least))


def _by_anchors(nodes: DataFrame, threshold: int) -> DataFrame:
    """Pairs of nodes to compare, found by the anchors: equal fingerprints and those that ``links`` joins."""
    fps = common.cut(nodes.groupBy("fp").agg(F.min("node").alias("low")))
    equal = nodes.join(fps, "fp").where("node <> low").select(F.col("node").alias("a"), F.col("low").alias("b"))
    near = links(fps.select("fp"), threshold)
    named = fps.select(F.col("fp").alias("a"), F.col("low").alias("la")), fps.select(F.col("fp").alias("b"), F.col("low").alias("lb"))
    joined = near.where("a <> b").join(named[0], "a").join(named[1], "b").select(F.col("la").alias("a"), F.col("lb").alias("b"))
    return equal.unionByName(joined)


def _by_three_holders(shared: DataFrame) -> DataFrame:
    """Pairs of each node with three holders of each of its keys, one of them the holder that shares most."""
    central = shared.groupBy("node").agg(F.sum("m").alias("weight"))
    low = F.xxhash64("node", F.lit(3))
    ends = shared.join(central, "node").groupBy("key").agg(F.max(F.struct("weight", "node")).alias("e1"), F.min("node").alias("e2"), F.min_by("node", low).alias("e3"))
    return shared.join(ends, "key").select(F.col("node").alias("a"), F.explode(F.array("e1.node", "e2", "e3")).alias("b")).where("a <> b")


def _by_every_holder(nodes: DataFrame, shared: DataFrame, found: DataFrame, at_least: float) -> DataFrame:
    """Pairs of each node with every holder of its keys that is in another component of ``found``."""
    rooted = shared.join(found, "node", "left").withColumn("root", F.coalesce("root", "node"))
    open_keys = rooted.groupBy("key").agg(F.min("root").alias("r1"), F.max("root").alias("r2")).where("r1 <> r2").select("key")
    held = common.cut(rooted.join(open_keys, "key").withColumn("many", F.ceil(F.col("m") / CELL)))
    spread = held.join(nodes.select("node", "n", "mark"), "node").withColumn("block", F.pmod(F.xxhash64("node"), "many")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("many") - 1)))
    cell = F.xxhash64("key", F.least("block", "other"), F.greatest("block", "other"))
    cells = spread.select(cell.alias("cell"), "block", (F.col("block") == F.col("other")).alias("inner"), "node", "root", "n", F.col("pos").cast("long").alias("pos"), *(F.col("mark")[i].alias(f"s{i}") for i in range(MARKS)))
    return cells.repartition("cell").sortWithinPartitions("cell").mapInArrow(partial(common.tidied, run=partial(_compare_cells, at_least=at_least)), "a long, b long")


def _classes(docs: DataFrame, id_col: str, text_col: str, words: int, at_least: float, threshold: int = 2) -> DataFrame:
    """(__id, __row, digest, root) for every row: rows of one root are linked."""
    common.tidy(docs.sparkSession)
    given = docs.select(F.col(id_col).alias("__id"), _row_key(id_col, text_col).alias("__row"), F.col(text_col).cast("string").alias("__text"))
    frequent = frequent_keys(given.select("__text"), words, at_least)
    fields = [("digest", T.StringType()), ("fp", T.LongType()), ("n", T.LongType()), ("mark", T.ArrayType(T.LongType())), ("first", T.ArrayType(T.LongType()))]
    rows = common.cut(common.with_text_columns(given, "__text", partial(_described, words=words, at_least=at_least, frequent=frequent), fields, keep=["__id", "__row"]))
    # numbers of rows stay as they are once the checkpoint holds them
    nodes = common.cut(rows.select("digest", "__row", "fp", "n", "mark", "first").dropDuplicates(["digest"]).withColumn("node", F.monotonically_increasing_id()))
    common.tidy(docs.sparkSession)

    def texts(of: DataFrame) -> DataFrame:
        rows_of = nodes.select("node", "__row").join(of, "node")
        near = common.may_hold(given.select("__row", F.col("__text").alias("text")), "__row", rows_of).where("__hit")
        return near.join(rows_of, "__row").dropDuplicates(["__row"]).select("node", "text")

    verified = partial(similar_pairs, texts=texts, words=words, at_least=at_least)
    held = nodes.select("node", F.posexplode("first").alias("pos", "key"))
    shared = common.cut(held.join(held.groupBy("key").agg(F.count("*").alias("m")).where("m > 1"), "key"))
    common.tidy(docs.sparkSession)
    met = _by_anchors(nodes, threshold).unionByName(_by_three_holders(shared)).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    size = nodes.select("node", "n", "mark")
    differ = F.aggregate(F.zip_with("ma", "mb", lambda x, y: F.bit_count(x.bitwiseXOR(y)).cast("int")), F.lit(0), lambda x, y: x + y)
    fit = (F.least("na", "nb") >= F.greatest("na", "nb") * at_least - 1e-6) & (differ <= (F.col("na") + F.col("nb")) * ((1 - at_least) / (1 + at_least) + 1e-12))
    edges = verified(met.join(size.toDF("a", "na", "ma"), "a").join(size.toDF("b", "nb", "mb"), "b").where(fit).select("a", "b"))
    found = common.cut(components(edges))
    more = verified(_by_every_holder(nodes, shared, found, at_least))
    if not more.isEmpty():
        found = common.cut(components(found.select(F.col("node").alias("a"), F.col("root").alias("b")).unionByName(more)))
    classes = nodes.join(found, "node", "left").select("digest", F.coalesce("root", "node").alias("root"))
    return rows.select("__id", "__row", "digest").join(classes, "digest")


def _row_key(id_col: str, text_col: str) -> F.Column:
    name = F.col(id_col).cast("string")
    return F.md5(F.concat(F.coalesce(F.concat(F.length(name).cast("string"), F.lit(":"), name), F.lit("-")), F.coalesce(F.col(text_col).cast("string"), F.lit(""))))


def similar_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 5, at_least: float = 0.8) -> DataFrame:
    """One row per document: id and ``component_id``, the smallest id reachable over texts whose
    similarity is ``at_least`` (null where no text of the component has an id).

    Texts with equal words are one node, whatever their ids.  The anchors of this module come first:
    nodes whose fingerprints over ``words`` words link at ``threshold`` bits are compared.  Similar
    texts can differ in more bits than anchors cover (about ten at 0.8), so an exact search completes
    the links: the shingles of all texts have one order, frequent ones last, and each node is held at
    its first fifth of them (``first_keys``), where similar nodes meet at one at least.  Each node is
    compared with three holders of each key, among them the one that shares most, which links most of
    a cluster by few pairs; then, at every key whose holders are not all linked, with every holder of
    another component, many holders dealt in blocks over cells, one for each two blocks.  Only pairs
    go whose sizes, places of the key or marks leave too few shingles to share; every other pair is
    compared exactly.  (Shingles meet by 64-bit hashes.)
    """
    rows = _classes(docs, id_col, text_col, words, at_least)
    low = rows.groupBy("root").agg(F.min("__id").alias("component_id"))
    return rows.join(low, "root").select(F.col("__id").alias(id_col), "component_id")


def _kept(docs: DataFrame, classes: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """Rows whose id is the smallest of its class, one for each id; rows without an id by equal text."""
    kept = classes.where(F.col(id_col) == F.col("component_id")).select(id_col).distinct()
    named = docs.join(kept, id_col, "left_semi").select(*docs.columns).dropDuplicates([id_col])
    return named.unionByName(docs.where(F.col(id_col).isNull()).dropDuplicates([text_col]))


def keep_similar(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """Of each group of similar texts the row with the smallest id; rows without an id come last, and
    of rows that share it the one with the least digest of its words stays."""
    rows = _classes(docs, id_col, text_col, **({"words": 5, "at_least": 0.8} | options))
    order = F.struct(F.col("__id").isNull().alias("unnamed"), "__id", "digest", "__row")
    kept = rows.groupBy("root").agg(F.min(order).alias("low"), F.count("*").alias("of")).select(F.col("low.__row").alias("__row"), "of")
    kept = common.cut(kept)
    # a document alone in its class stays without a join; the others meet the one that is kept
    grouped = rows.join(kept.where("of = 1").select("__row"), "__row", "left_anti").select("__row")
    named = common.may_hold(docs.withColumn("__row", _row_key(id_col, text_col)), "__row", grouped)
    chosen = named.where("__hit").join(kept.select("__row"), "__row", "left_semi").dropDuplicates(["__row"])
    return named.where("NOT __hit").select(*docs.columns).unionByName(chosen.select(*docs.columns))


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """The documents whose id is the smallest of their component; of rows that share that id, one."""
    return _kept(docs, near_duplicates(docs, id_col, text_col, **options), id_col, text_col)
