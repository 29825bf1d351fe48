"""Structure learner: groups of sensors from their embeddings, as a tall membership relation."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from decimal import ROUND_HALF_UP, Context, Decimal
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window, functions as F, types as T
from pyspark.sql.pandas.types import to_arrow_schema

from polyedge.functions import algebra as A
from polyedge.session import materialise, ship

#: rows of a packed block: queries and the nodes they are held against
QUERY_BLOCK, NODE_BLOCK = 256, 2048
#: tasks that a query's nodes are dealt to at most: each returns its k best, so what is shuffled grows with the queries
NODE_PARTS = 32
#: share of the squared lengths by which a squared distance from a matrix product may be wrong, and what counts as too large for it
SLACK, LARGE = 1e-10, 1e300
MANY_DIGITS = Context(prec=400)
PAIR = ("block", "q_ids", "q", "r_ids", "r")
#: noise of a pair (i, j): how many values it has, the factors of i and j, and the step between two draws
NOISES, OF_I, OF_J, SALT = 99_991, 7919, 104_729, 15_485_863


def pair_distances(nodes: DataFrame, d: int | None = None, queries: DataFrame | None = None) -> DataFrame:
    """(i, j, dist) for i <> j: n squared rows, for sensor lists.  Spark broadcasts a side only if its
    size is under the session's bound.  With ``queries`` i is one of these and blocks are compared."""
    if queries is not None:
        return nearest(queries, nodes, None)
    if d is None:
        d = nodes.agg(F.max(F.size("z"))).first()[0] or 0
    a, b = nodes.select(F.col("sensor_id").alias("i"), F.col("z").alias("zi")), nodes.select(F.col("sensor_id").alias("j"), F.col("z").alias("zj"))
    return a.join(b, F.col("i") != F.col("j")).select("i", "j", _distance(d).alias("dist"))


def _distance(d: int) -> Column:
    """Distance of ``zi`` and ``zj`` term by term, which compiles where an array lambda would not."""
    if d > 256:
        return A.distance(F.col("zi"), F.col("zj"))
    total = F.lit(0.0)
    for k in range(d):
        gap = F.col("zi")[k] - F.col("zj")[k]
        total = total + gap * gap
    return F.sqrt(total)


def _packed(batches: Iterator[pa.RecordBatch], block: int) -> Iterator[pa.RecordBatch]:
    """Rows of (sensor_id, z) as blocks: ids and vectors, in bytes."""
    for b in batches:
        for at in range(0, b.num_rows, block):
            ids, z = b.column(0)[at : at + block], b.column(1)[at : at + block]
            yield pa.RecordBatch.from_arrays([pa.array([ids.to_numpy(zero_copy_only=False).astype(np.int64).tobytes()]), pa.array([z.flatten().to_numpy(zero_copy_only=False).astype(np.float64).tobytes()])], names=["ids", "z"])


class _Best:
    """The k nearest of a block of queries among the nodes met so far, ties by id.

    A matrix product gives a lower bound of each squared distance; what it doesn't put beyond the k-th
    distance is measured term by term in order, as SQL sums it.  No number counts as the farthest.
    """

    room = np.empty((0, 0))  # for the bounds of some queries, used again by every block of a worker

    def __init__(self, ids: np.ndarray, q: np.ndarray, k: int):
        self.ids, self.q, self.k, self.qq = ids, q, k, (q * q).sum(1)
        self.odd = not self.qq.max() < LARGE
        self.left = np.column_stack([q, np.ones(len(q)), self.qq * (1 - SLACK)])
        self.dist, self.near, self.count = np.empty((len(q), k)), np.empty((len(q), k), np.int64), np.zeros(len(q), np.int64)
        self.bound = np.full(len(q), np.inf)
        self.below = np.full(len(q), np.iinfo(np.int64).max)  # of k copies at distance 0, the last id

    def meet(self, r_ids: np.ndarray, r: np.ndarray) -> None:
        rr = (r * r).sum(1)
        odd = self.odd or not rr.max() < LARGE
        turned = np.vstack([-2 * r.T, rr * (1 - SLACK), np.ones(len(r))])
        if self.room.shape[1] != len(r):
            _Best.room = np.empty((128, len(r)))
        for at in range(0, len(self.q), 128):
            part = slice(at, min(at + 128, len(self.q)))
            low = np.matmul(self.left[part], turned, out=self.room[: part.stop - at])
            if odd:
                low[~np.isfinite(low)] = -np.inf
            found = self._open(np.flatnonzero(low <= self.bound[part, None]), at, r_ids)
            if len(found) > 4 * self.k * len(low) and self.k < len(r) and not odd:
                low[self.ids[part, None] == r_ids] = np.inf
                kth = np.partition(low, self.k - 1, axis=1)[:, self.k - 1]
                found = self._open(np.flatnonzero(low <= np.minimum(self.bound[part], kth + 2 * SLACK * (self.qq[part] + rr.max()))[:, None]), at, r_ids)
            for some in range(0, len(found), 65_536):
                row, col = np.divmod(found[some : some + 65_536], len(r))
                self._keep(at + row, r_ids[col], r, col)

    def _open(self, found: np.ndarray, at: int, r_ids: np.ndarray) -> np.ndarray:
        row, col = np.divmod(found, len(r_ids))
        return found[r_ids[col] < self.below[at + row]]

    def _keep(self, row: np.ndarray, ids: np.ndarray, r: np.ndarray, col: np.ndarray) -> None:
        other = self.ids[row] != ids
        row, ids, col = row[other], ids[other], col[other]
        dist = np.empty(len(row))
        for at in range(0, len(row), 16_384):
            dist[at : at + 16_384] = _gaps(self.q[row[at : at + 16_384]], r[col[at : at + 16_384]])
        touched = np.unique(row)
        if not len(touched):
            return
        held_row, held_at = np.nonzero(np.arange(self.k) < self.count[touched, None])
        held_row = touched[held_row]
        row, dist, ids = np.concatenate([held_row, row]), np.concatenate([self.dist[held_row, held_at], dist]), np.concatenate([self.near[held_row, held_at], ids])
        order = np.lexsort((ids, dist, row))
        row, dist, ids = row[order], dist[order], ids[order]
        place = np.arange(len(row)) - np.searchsorted(row, row)
        keep = place < self.k
        self.dist[row[keep], place[keep]], self.near[row[keep], place[keep]] = dist[keep], ids[keep]
        self.count[touched] = np.bincount(np.searchsorted(touched, row[keep]))
        full = touched[self.count[touched] == self.k]
        last = self.dist[full, self.k - 1]
        self.bound[full] = np.where(np.isfinite(last), last * last * (1 + SLACK), np.inf)
        self.below[full[last == 0]] = self.near[full[last == 0], self.k - 1]

    def rows(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        row, at = np.nonzero(np.arange(self.k) < self.count[:, None])
        return self.ids[row], self.near[row, at], self.dist[row, at]


def _gaps(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Distance of each row of ``x`` and the same row of ``y``, term by term."""
    gap = x - y
    total = np.zeros(len(gap))
    for k in range(gap.shape[1]):
        total += gap[:, k] * gap[:, k]
    return np.sqrt(total)


def rounded(x: np.ndarray, digits: int) -> np.ndarray:
    """Numbers from 0 on, rounded as Spark rounds: half up by the decimal form, which is asked only near a half."""
    scaled = x * 10.0**digits
    whole = np.floor(scaled)
    part = scaled - whole
    out = (whole + (part >= 0.5)) / 10.0**digits
    for at in np.flatnonzero(~(np.abs(part - 0.5) > 1e-9 + scaled * 1e-15)).tolist():
        v = float(x[at])
        out[at] = float(Decimal(repr(v)).quantize(Decimal(1).scaleb(-digits), ROUND_HALF_UP, MANY_DIGITS)) if np.isfinite(v) else v
    return out


def _all(q_ids: np.ndarray, q: np.ndarray, r_ids: np.ndarray, r: np.ndarray, digits: int | None = None) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(i, j, dist) of all pairs of different ids, a few queries at a time, term by term as SQL sums it."""
    turned = np.ascontiguousarray(r.T)
    for at in range(0, len(q), 16):
        total = np.zeros((len(q[at : at + 16]), len(r)))
        for x in range(q.shape[1]):
            gap = q[at : at + 16, x, None] - turned[x]
            gap *= gap
            total += gap
        row, col = np.nonzero(q_ids[at : at + 16, None] != r_ids)
        dist = np.sqrt(total)[row, col]
        yield q_ids[at + row], r_ids[col], dist if digits is None else rounded(dist, digits)


def _noise(place: np.ndarray) -> np.ndarray:
    return -np.log(-np.log((place % NOISES + 1) / (NOISES + 2.0)))


def _drawn(q_ids: np.ndarray, q: np.ndarray, r_ids: np.ndarray, r: np.ndarray, temperature: float, seed: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(i, j) that two-class Gumbel noise draws, some queries at a time.

    Noise has one value for each remainder.  A squared distance by a matrix product decides, except
    within its rounding of the border, where the term-by-term distance does.
    """
    first, second = (_noise(np.arange(2 * NOISES) + seed * 31 + salt * SALT) for salt in (1, 2))
    reach = 1.0 + temperature * (first - second)
    border = reach * np.abs(reach)
    a, b = q_ids % NOISES * OF_I % NOISES, r_ids % NOISES * OF_J % NOISES
    qq, rr = (q * q).sum(1), (r * r).sum(1)
    slack = 1e-9 * (1 + qq.max() + rr.max() + np.abs(border).max())
    for at in range(0, len(q), 32):
        place = a[at : at + 32, None] + b
        gap = border.take(place)
        gap -= qq[at : at + 32, None] + rr - 2 * (q[at : at + 32] @ r.T)
        drawn = gap > 0
        row, col = np.nonzero(~(np.abs(gap) > slack))  # also what is no number
        if len(row):
            of = place[row, col]
            drawn[row, col] = ~(-_gaps(q[at + row], r[col]) / temperature + 1.0 / temperature + first[of] <= second[of])
        drawn &= q_ids[at : at + 32, None] != r_ids
        row, col = np.nonzero(drawn)
        yield q_ids[at + row], r_ids[col]


def _block(ids: pa.Scalar, z: pa.Scalar) -> tuple[np.ndarray, np.ndarray]:
    at = np.frombuffer(ids.as_buffer(), np.int64)
    return at, np.frombuffer(z.as_buffer()).reshape(len(at), -1)


def _batch(columns: tuple[np.ndarray, ...], schema: pa.Schema) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(v.astype(f.type.to_pandas_dtype(), copy=False)) for v, f in zip(columns, schema, strict=True)], schema=schema)


def _compared(batches: Iterator[pa.RecordBatch], found: Callable, schema: pa.Schema) -> Iterator[pa.RecordBatch]:
    for b in batches:
        for _, q_ids, q, r_ids, r in zip(*(b[c] for c in PAIR), strict=True):
            for columns in found(*_block(q_ids, q), *_block(r_ids, r)):
                yield _batch(columns, schema)


def _searched(batches: Iterator[pa.RecordBatch], k: int, schema: pa.Schema) -> Iterator[pa.RecordBatch]:
    """The k best of each query among all the nodes that a task meets."""
    held: dict[int, _Best] = {}
    for b in batches:
        for block, q_ids, q, r_ids, r in zip(*(b[c] for c in PAIR), strict=True):
            if (at := block.as_py()) not in held:
                held[at] = _Best(*(x.copy() for x in _block(q_ids, q)), k)
            held[at].meet(*_block(r_ids, r))
    for best in held.values():
        yield _batch(best.rows(), schema)


def _by_blocks(queries: DataFrame, nodes: DataFrame, found: Callable, with_dist: bool = True, parts: int | None = None, of: int = QUERY_BLOCK) -> DataFrame:
    """What ``found`` gives for the pairs of a block of queries and a block of nodes; nodes without a vector are in none.
    A task holds its blocks of queries, ``of`` rows each, while nodes pass by, in ``parts`` partitions at most."""
    ship(nodes.sparkSession)
    nodes_ = nodes.coalesce(parts) if parts else nodes
    q, r = (df.where("z IS NOT NULL").select("sensor_id", "z").mapInArrow(partial(_packed, block=n), "ids binary, z binary") for df, n in ((queries, of), (nodes_, NODE_BLOCK)))
    pairs = r.toDF("r_ids", "r").crossJoin(q.toDF("q_ids", "q").withColumn("block", F.monotonically_increasing_id()))
    kind = nodes.schema["sensor_id"].dataType
    names = T.StructType([T.StructField("i", kind), T.StructField("j", kind), *[T.StructField("dist", T.DoubleType())] * with_dist])
    return pairs.mapInArrow(partial(found, schema=to_arrow_schema(names)), names)


def nearest(queries: DataFrame, nodes: DataFrame, k: int | None, digits: int | None = None) -> DataFrame:
    """(i, j, dist) that holds the k nearest nodes of each query, or all (None), by blocks of both: of a
    task only the k best of each query leave it, so pairs are neither shuffled nor sorted.
    Nodes without a vector have no distance.  ``digits`` rounds the distances of all."""
    if k is None:
        return _by_blocks(queries, nodes, partial(_compared, found=partial(_all, digits=digits)))
    return _by_blocks(queries, nodes, partial(_searched, k=k), parts=NODE_PARTS, of=4 * QUERY_BLOCK)


def knn(dist: DataFrame, k: int) -> DataFrame:
    """(edge_id, sensor_id, rank, dist): the k nearest of each node, ties by id."""
    w = Window.partitionBy("i").orderBy("dist", "j")
    near = dist.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)
    return near.select(F.col("i").alias("edge_id"), F.col("j").alias("sensor_id"), F.col("rank").cast("int").alias("rank"), "dist")


def uniform_members(nodes: DataFrame, k: int, queries: DataFrame | None = None) -> DataFrame:
    """Edge p is node p with its k nearest nodes: n(k+1) memberships, all of size k+1.  With
    ``queries`` only these have edges, over all nodes, found block by block."""
    own = (nodes if queries is None else queries).select(F.col("sensor_id").alias("edge_id"), "sensor_id", F.lit(0).alias("rank"), F.lit(0.0).alias("dist"))
    return own.unionByName(knn(pair_distances(nodes) if queries is None else nearest(queries, nodes, k), k))


def mutual_members(nodes: DataFrame, k: int, queries: DataFrame) -> DataFrame:
    """Memberships (edge_id, sensor_id) of the queries' edges whose reverse is one too: the edges of the
    members are found as well, and no others."""
    found = materialise(uniform_members(nodes, k, queries).select("edge_id", "sensor_id"))
    others = nodes.join(found.select("sensor_id").distinct(), "sensor_id", "left_semi")
    turned = uniform_members(nodes, k, others).select(F.col("sensor_id").alias("edge_id"), F.col("edge_id").alias("sensor_id"))
    return found.join(turned, ["edge_id", "sensor_id"], "left_semi")


def _both_ways(members: DataFrame, edge: str, sensor: str) -> DataFrame:
    """Each membership as (edge, sensor) and as (sensor, edge), from one pass over ``members``."""
    ways = [F.struct(F.col(a).alias(edge), F.col(b).alias(sensor)) for a, b in (("edge_id", "sensor_id"), ("sensor_id", "edge_id"))]
    return members.select(F.inline(F.array(*ways)))


def symmetrise(members: DataFrame, mode: str) -> DataFrame:
    """``none``; ``union`` adds the reverse of every membership; ``mutual`` keeps those that have one."""
    if mode == "none":
        return members
    if mode == "union":
        return _both_ways(members, "edge_id", "sensor_id").distinct()
    if mode == "mutual":
        turned = members.select(F.col("sensor_id").alias("edge_id"), F.col("edge_id").alias("sensor_id"))
        return members.select("edge_id", "sensor_id").join(turned, ["edge_id", "sensor_id"], "left_semi")
    raise ValueError("symmetry is none, union or mutual")


def irregular_members(nodes: DataFrame, temperature: float = 0.2, seed: int = 1, queries: DataFrame | None = None) -> DataFrame:
    """Memberships drawn by two-class Gumbel noise on similarity; size varies, the centre stays.

    Noise comes from integer arithmetic on (i, j, seed), so every engine draws the same.  With
    ``queries`` blocks are compared, and only what is drawn leaves them.
    """
    def noise(salt: int):
        i, j = (F.pmod(F.col(c).cast("long"), F.lit(NOISES)) for c in ("i", "j"))
        u = (F.pmod(i * OF_I + j * OF_J + F.lit(seed * 31 + salt * SALT), F.lit(NOISES)) + 1) / F.lit(NOISES + 2.0)
        return -F.log(-F.log(u))

    if queries is not None:
        drawn = _by_blocks(queries, nodes, partial(_compared, found=partial(_drawn, temperature=temperature, seed=seed)), False)
    else:
        logit = -F.col("dist") / F.lit(temperature) + F.lit(1.0 / temperature)
        drawn = pair_distances(nodes).where(logit + noise(1) > noise(2))
    drawn = drawn.select(F.col("i").alias("edge_id"), F.col("j").alias("sensor_id"))
    return (nodes if queries is None else queries).select(F.col("sensor_id").alias("edge_id"), "sensor_id").unionByName(drawn)


def build(nodes: DataFrame, kind: str = "uniform", k: int = 1, symmetry: str = "none", temperature: float = 0.2, seed: int = 1, queries: DataFrame | None = None) -> DataFrame:
    """(edge_id, sensor_id) of any variant; ``pair`` edges have a centre and its nearest node.  With
    ``queries`` only these nodes have edges."""
    if kind == "irregular":
        return irregular_members(nodes, temperature, seed, queries)
    if queries is not None and symmetry == "mutual":
        return mutual_members(nodes, 1 if kind == "pair" else k, queries)
    members = uniform_members(nodes, 1 if kind == "pair" else k, queries)
    return symmetrise(members, symmetry).select("edge_id", "sensor_id")


def neighbourhoods(members: DataFrame) -> DataFrame:
    """Per node: members of its own edge, these less itself, the edges it is in, and their numbers
    (null for what a node has none of)."""
    node, sensor, edge = F.col("edge_id").alias("node"), F.col("sensor_id"), F.col("edge_id")
    none = [F.lit(None).cast(members.schema[c].dataType) for c in ("sensor_id", "edge_id")]
    ways = members.select(F.inline(F.array(F.struct(node, sensor.alias("member"), none[1].alias("edge")), F.struct(sensor.alias("node"), none[0].alias("member"), edge.alias("edge")))))
    lists = ways.groupBy("node").agg(*[F.sort_array(F.collect_list(c)).alias(name) for c, name in (("member", "members"), ("edge", "edges"))])
    both = lists.select("node", *[F.when(F.size(c) > 0, F.col(c)).alias(c) for c in ("members", "edges")])
    return both.select("node", "members", F.array_except("members", F.array("node")).alias("local"), "edges", *[F.when(F.col(c).isNotNull(), F.size(c)).alias(name) for c, name in (("members", "cardinality"), ("edges", "degree"))])


def _edges_of_nodes(members: DataFrame, nodes: DataFrame | None) -> DataFrame:
    held = members.groupBy("sensor_id").agg(F.collect_set("edge_id").alias("e"))
    if nodes is not None:
        held = nodes.select("sensor_id").join(held, "sensor_id", "left").withColumn("e", F.coalesce("e", F.array().cast("array<int>")))
    return held


def dense_incidence(members: DataFrame, n: int, every: int = 1, nodes: DataFrame | None = None) -> DataFrame:
    """Rows of the 0/1 incidence matrix, of every ``every``-th edge; with ``nodes`` also the rows without a 1."""
    held = _edges_of_nodes(members, nodes)
    return held.select("sensor_id", F.transform(F.sequence(F.lit(0), F.lit(n - 1), F.lit(every)), lambda p: F.array_contains("e", p).cast("int")).alias("row"))


def incidence_digits(members: DataFrame, n: int, every: int = 1, nodes: DataFrame | None = None) -> DataFrame:
    """``dense_incidence`` with each row as a string of its digits, made from the runs of zeros between the ones."""
    inside = F.filter("e", lambda p: (p % every == 0) & (p >= 0) & (p < n))
    held = _edges_of_nodes(members, nodes).select("sensor_id", F.array_sort(F.transform(inside, lambda p: (p / every).cast("int"))).alias("at"))
    zeros = lambda last, p: F.repeat(F.lit("0"), p - F.coalesce(F.get("at", last), F.lit(-1)) - 1)
    ones = F.transform("at", lambda p, k: F.concat(zeros(k - 1, p), F.lit("1")))
    return held.select("sensor_id", F.concat(F.array_join(ones, ""), zeros(F.size("at") - 1, F.lit(len(range(0, n, every))))).alias("row"))


def knn_lsh(nodes: DataFrame, k: int, bucket: float | None = None, tables: int = 8, radius: float = math.inf) -> DataFrame:
    """Approximate neighbours for very many nodes by random projection buckets."""
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector

    v = nodes.select("sensor_id", array_to_vector("z").alias("v"))
    model = BucketedRandomProjectionLSH(inputCol="v", outputCol="h", bucketLength=bucket or 1.0, numHashTables=tables, seed=1).fit(v)
    near = model.approxSimilarityJoin(v, v, radius if math.isfinite(radius) else 1e9, "dist")
    pairs = near.select(F.col("datasetA.sensor_id").alias("i"), F.col("datasetB.sensor_id").alias("j"), "dist").where("i <> j")
    return knn(pairs, k)
