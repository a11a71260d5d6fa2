"""Approximate nearest neighbours by collision-counting hashing.

The vectors are dealt into shards; each shard keeps one sorted array for every
projection line.  A query opens a window around its own projection on each line
and widens all windows step by step (virtual rehashing: only the two new strips
of each array are read).  A vector that falls into the windows of enough lines - the
collision threshold of the step, set above what a far vector usually reaches - is
verified with its exact inner product; others are not looked at.  A shard's search
stops when a vector as near as the current k-th best would have passed the threshold
with probability ``sure``; later steps ask for less, and only if even the last one
does not tell near from far are the remaining vectors verified.  Every row is
indexed; nothing is capped.

Largest inner product becomes nearest by one more coordinate: a shard's vectors
are lifted to equal norm, and queries are scaled to that norm.

A shard crosses the network once for each lane (lanes only where shards are fewer
than the exchange's partitions), a block of queries once for each shard.

Cases: vectors that are null, zero, or hold null or non-finite components take no
part; vectors of different lengths are not compared; equal vectors tie and the
smaller id comes first; fewer candidates than ``k`` give fewer rows; an empty table
gives none; null ids take no part; further columns are not read.
"""

from __future__ import annotations

import math
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import n_buckets, spool

K, EVERY, SHARD_ROWS, QUERY_ROWS, SURE, SEED = 20, 20, 16_384, 512, 0.9, 7
SCHEMA = "query_id long, block long, vec_id long, score double, verified long"
#: Lines a vector is projected on, at least.
LINES = 128


def usable(vectors: DataFrame, id_col: str, vec: str) -> DataFrame:
    """Rows that take part, as ``vec_id`` and ``v`` (array of double)."""
    v = F.col(vec).cast("array<double>")
    ok = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf"))) & F.exists(v, lambda x: x != 0)
    return vectors.select(F.col(id_col).cast("long").alias("vec_id"), v.alias("v")).where(F.col("vec_id").isNotNull() & ok)


def _phi(x: np.ndarray) -> np.ndarray:
    """Normal distribution function, to about 1e-7."""
    z = np.abs(x)
    t = 1 / (1 + 0.2316419 * z)
    tail = np.exp(-z * z / 2) / math.sqrt(2 * math.pi) * t * (0.319381530 + t * (-0.356563782 + t * (1.781477937 + t * (-1.821255978 + t * 1.330274429))))
    return np.where(x >= 0, 1 - tail, tail)


#: Steps: half width of the windows in units of the shard's norm, and by how many standard
#: deviations of a far (orthogonal) vector's count the threshold lies above its mean.
STEPS = ((0.6, 1.5), (0.7, 1.2), (0.8, 0.9), (0.9, 0.6), (1.0, 0.3), (1.1, 0.0))
#: Counts on orthogonal lines vary less than independent trials would.
SPREAD = 0.8


class Shard:
    """Sorted projections of up to ``SHARD_ROWS`` vectors."""

    def __init__(self, ids: np.ndarray, x: np.ndarray):
        self.ids, self.x = ids, x
        norms = (x * x).sum(1)
        self.top = math.sqrt(norms.max())
        lifted = np.hstack([x, np.sqrt(np.maximum(self.top**2 - norms, 0))[:, None]])
        d = lifted.shape[1]
        rng, m = np.random.default_rng(SEED), LINES
        turns = [np.linalg.qr(rng.normal(size=(d, d)))[0] for _ in range(-(-m // d))]
        self.turn = np.hstack(turns)[:, :m] * math.sqrt(d)  # a projection's spread is the distance
        p = (lifted @ self.turn).T
        self.order = np.argsort(p, axis=1, kind="stable").astype(np.int32)
        self.sorted = np.take_along_axis(p, self.order, 1)

    def _need(self, width: float, above: float) -> int:
        """Windows that a vector must fall into: more than a far one usually does."""
        m, p = len(self.order), float(2 * _phi(np.array(width / math.sqrt(2))) - 1)
        return max(1, math.ceil(m * p + above * SPREAD * math.sqrt(m * p * (1 - p))))

    def search(self, qids: list[int], qs: np.ndarray, k: int, sure: float = SURE) -> Iterator[tuple]:
        """``(query id, ids, scores, number verified)`` of each query, nearest first."""
        n, m, steps = len(self.ids), len(self.order), len(STEPS)
        size = np.sqrt((qs * qs).sum(1))
        at = (qs * (self.top / size)[:, None]) @ self.turn[: qs.shape[1]]
        lo = np.empty((steps, m, len(qs)), np.int64)
        hi = np.empty_like(lo)
        for w, (width, _) in enumerate(STEPS):
            for i in range(m):
                lo[w, i] = np.searchsorted(self.sorted[i], at[:, i] - width * self.top, "left")
                hi[w, i] = np.searchsorted(self.sorted[i], at[:, i] + width * self.top, "right")
        need = [self._need(*s) for s in STEPS]
        z = 1.28 if sure <= 0.9 else 1.65 if sure <= 0.95 else 2.33
        for j, (qid, q) in enumerate(zip(qids, qs, strict=True)):
            seen, done = np.zeros(n, np.int64), np.zeros(n, bool)
            rows, scores, verified = np.empty(0, np.int64), np.empty(0), 0
            for w in range(steps + 1):
                if w < steps:
                    strips = []
                    for i in range(m):
                        order, l, h = self.order[i], lo[w, i, j], hi[w, i, j]
                        if w:
                            strips += [order[l : lo[w - 1, i, j]], order[hi[w - 1, i, j] : h]]
                        else:
                            strips.append(order[l:h])
                    seen += np.bincount(np.concatenate(strips), minlength=n)
                    fresh = (seen >= need[w]) & ~done
                else:
                    fresh = ~done
                done |= fresh
                found = np.flatnonzero(fresh)
                found = found[self.ids[found] != qid]
                if len(found):
                    verified += len(found)
                    rows, scores = np.append(rows, found), np.append(scores, self.x[found] @ q)
                    if len(rows) > k:
                        edge = np.partition(scores, len(scores) - k)[len(scores) - k]
                        near = scores >= edge - 1e-9 * max(1.0, abs(edge))
                        rows, scores = rows[near], scores[near]
                if w < steps and len(rows) >= k:
                    cos = scores.min() / (size[j] * self.top)
                    p = float(2 * _phi(np.array(STEPS[w][0] / math.sqrt(max(2 - 2 * cos, 1e-9)))) - 1)
                    if m * p - z * SPREAD * math.sqrt(m * p * (1 - p)) >= need[w]:
                        break
            exact = (self.x[rows] * q).sum(1)
            best = np.lexsort((self.ids[rows], -exact))[:k]
            yield qid, self.ids[rows][best], exact[best], verified


def _search_blocks(k: int, sure: float):
    """Rows sorted so that a shard (kind 0) stands before the blocks of queries that visit it."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shard = None
        for b in batches:
            c = dict(zip(b.schema.names, b.columns, strict=True))
            for i in range(b.num_rows):
                ids = np.frombuffer(c["ids"][i].as_buffer(), np.int64)
                x = np.frombuffer(c["x"][i].as_buffer(), np.float64).reshape(-1, c["d"][i].as_py())
                if c["kind"][i].as_py() == 0:
                    shard = Shard(ids, x)
                    continue
                block, out = c["block"][i].as_py(), [[], [], [], []]
                for qid, got, score, verified in shard.search(ids.tolist(), x, k, sure):
                    out[0] += [qid] * len(got)
                    out[1] += got.tolist()
                    out[2] += score.tolist()
                    out[3] += [verified] * bool(len(got)) + [0] * (len(got) - 1)
                yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.int64()), pa.array([block] * len(out[0]), pa.int64()), pa.array(out[1], pa.int64()), pa.array(out[2], pa.float64()), pa.array(out[3], pa.int64())], ["query_id", "block", "vec_id", "score", "verified"])

    return run


def _pack(size: int):
    """Rows of a task to packed blocks of ``size``, one length of vector each."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        held: dict[int, tuple[list, list]] = {}
        pid, seq = TaskContext.get().partitionId(), 0

        def block(d: int):
            nonlocal seq
            ids, xs = held.pop(d)
            seq += 1
            return pa.RecordBatch.from_arrays([pa.array([(pid << 32) | seq], pa.int64()), pa.array([d], pa.int32()), pa.array([np.array(ids, np.int64).tobytes()], pa.binary()), pa.array([np.array(xs, np.float64).tobytes()], pa.binary())], ["block", "d", "ids", "x"])

        for b in batches:
            for i, v in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                ids, xs = held.setdefault(len(v), ([], []))
                ids.append(i)
                xs.append(v)
                if len(ids) == size:
                    yield block(len(v))
        for d in list(held):
            yield block(d)

    return run


def nearest(
    vectors: DataFrame, id_col: str = "vec_id", vec: str = "embedding", k: int = K, every: int = EVERY,
    shard_rows: int = SHARD_ROWS, sure: float = SURE,
) -> DataFrame:
    """``query_id, rank, vec_id, score, n_verified`` of the rows whose id ``every`` divides;
    the last is the number of inner products taken for the query."""
    spark = vectors.sparkSession
    rows = usable(vectors, id_col, vec)
    n = rows.count()
    kind = "block long, d int, ids binary, x binary"
    index = spool(rows.repartition(max(1, -(-n // shard_rows))).mapInArrow(_pack(2 * shard_rows), kind), "vector-shards")
    shards, buckets = max(1, index.count()), n_buckets(spark)
    lanes = -(-buckets // shards)
    asked = rows.where(F.col("vec_id") % every == 0).repartition(max(1, lanes, -(-n // (every * QUERY_ROWS))))
    asked = asked.mapInArrow(_pack(QUERY_ROWS), kind)
    held = index.select("block", "d", F.explode(F.sequence(F.lit(0), F.lit(lanes - 1))).alias("lane"), F.lit(0).alias("kind"), "ids", "x")
    # by length; ids and lengths of shards only, one row for ``shard_rows`` vectors
    visits = asked.withColumnRenamed("block", "q").join(F.broadcast(index.select("block", "d")), "d").select("block", "d", F.pmod(F.xxhash64("q"), F.lit(lanes)).cast("int").alias("lane"), F.lit(1).alias("kind"), "ids", "x")
    both = held.unionByName(visits).repartition(max(buckets, shards * lanes), "block", "lane").sortWithinPartitions("block", "lane", "kind")
    found = both.mapInArrow(_search_blocks(k, sure), SCHEMA)
    best = F.slice(F.sort_array(F.collect_list(F.struct((-F.col("score")).alias("s"), "vec_id"))), 1, k)
    # the best of some shards first: no group holds all shards' answers to a query
    some = found.groupBy("query_id", F.pmod(F.xxhash64("block"), F.lit(math.isqrt(shards - 1) + 1)).alias("part")).agg(best.alias("b"), F.sum("verified").alias("verified"))
    top = some.groupBy("query_id").agg(F.slice(F.sort_array(F.flatten(F.collect_list("b"))), 1, k).alias("b"), F.sum("verified").alias("n_verified"))
    top = top.select("query_id", "n_verified", F.posexplode("b").alias("p", "e"))
    return top.select("query_id", (F.col("p") + 1).cast("int").alias("rank"), F.col("e.vec_id").alias("vec_id"), (-F.col("e.s")).alias("score"), "n_verified")


def nearest_exact(vectors: DataFrame, id_col: str = "vec_id", vec: str = "embedding", k: int = K, every: int = EVERY) -> DataFrame:
    """Brute force, for measuring recall on small tables."""
    rows = usable(vectors, id_col, vec)
    q = rows.where(F.col("vec_id") % every == 0).select(F.col("vec_id").alias("query_id"), F.col("v").alias("q"))
    dot = F.aggregate(F.zip_with("q", "v", lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x)
    every_pair = q.join(rows, (F.col("query_id") != F.col("vec_id")) & (F.size("q") == F.size("v")))
    from pyspark.sql import Window

    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return every_pair.select("query_id", "vec_id", dot.alias("score")).withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)
