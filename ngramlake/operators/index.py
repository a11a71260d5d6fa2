"""The sorted window array: distinct windows with run lengths, in blocks under fences.

``runs`` is range-partitioned and sorted by key: ``block, rank, key, run``.  ``blocks``
is what lookups read: one row a block, its keys front-coded (each key as the prefix
shared with the key before it, and the rest), with the number of windows before it and
the first key after it, in folders by ``shard`` (a run of blocks) so that a lookup lists
only the folders it needs.  Fences are the first key of every block.  ``postings`` hold
each window's places by rank, without its key.  Windows at a document's end are kept
shorter.  Documents that come later make an index of their own among ``deltas``, which
every lookup asks too, until ``compact_index`` merges them.
"""

from __future__ import annotations

import time
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ngramlake.functions.text import key_of
from ngramlake.operators.vocab import add_rank
from ngramlake.sources.tables import spool

WINDOW, BLOCK = 10, 4096
#: Memory for the fences of an index whose block size is chosen from its size.
FENCE_MEMORY = 256 << 20
#: Least blocks in a shard, most shards of an index.
SHARD_BLOCKS, SHARDS = 256, 10_000


def windows(corpus: DataFrame, length: int = WINDOW, keep_tail: bool = True) -> DataFrame:
    """``doc_id, pos, key`` of the window from every position."""
    size = F.size("tokens")
    last = size - 1 if keep_tail else size - length
    own = F.transform(F.sequence(F.lit(0), last), lambda i: key_of(F.slice("tokens", i + 1, length)))
    return corpus.where(last >= 0).select("doc_id", F.posexplode(own).alias("pos", "key"))


def choose_block(n: int, key_bytes: int, memory: int) -> int:
    """Least power of two whose fences fit the memory."""
    b = 1
    while n / b * key_bytes > memory:
        b *= 2
    return b


@dataclass
class WindowIndex:
    runs: DataFrame
    blocks: DataFrame
    fences: DataFrame
    postings: DataFrame | None
    length: int
    block: int
    shard: int = SHARD_BLOCKS
    seconds: float = 0.0
    deltas: tuple[WindowIndex, ...] = ()
    held: dict = field(default_factory=dict, repr=False)

    @property
    def spark(self) -> SparkSession:
        return self.runs.sparkSession

    @property
    def parts(self) -> tuple[WindowIndex, ...]:
        return (self, *self.deltas)


def compress_runs(rows: DataFrame) -> DataFrame:
    """``key, run``: equal windows as one row (partial counts before the shuffle)."""
    return rows.groupBy("key").agg(F.count("*").alias("run"))


def prefix_code(runs: DataFrame) -> DataFrame:
    """``block, rank, shared, rest``: each key as the prefix shared with the key before
    it in its block, and what follows, as columns (the blocks hold the same, packed)."""
    before = F.lag("key").over(Window.partitionBy("block").orderBy("rank"))
    x = runs.withColumn("_b", F.coalesce(before, F.lit("")))
    n = F.least(F.length("key"), F.length("_b"))
    differ = F.filter(F.sequence(F.lit(1), F.greatest(n, F.lit(1))), lambda i: F.substring(F.col("key"), i, F.lit(1)) != F.substring(F.col("_b"), i, F.lit(1)))
    shared = F.when(n == 0, 0).otherwise(F.coalesce(F.get(differ, 0) - 1, n))
    x = x.withColumn("shared", shared)
    return x.select("block", "rank", "run", "shared", F.expr("substring(key, shared + 1)").alias("rest"))


def encode_block(keys: list[bytes], runs: Iterable[int]) -> bytes:
    """Sorted keys front-coded, with their runs."""
    same, last = [], b""
    for k in keys:
        n = min(len(k), len(last))
        x = int.from_bytes(k[:n], "big") ^ int.from_bytes(last[:n], "big")
        same.append(n - ((x.bit_length() + 7) >> 3))
        last = k
    sizes = np.fromiter(map(len, keys), np.uint32, len(keys))
    heads = np.array(same, np.uint32)
    tails = b"".join([k[s:] for k, s in zip(keys, same, strict=True)])
    return len(keys).to_bytes(4, "little") + heads.tobytes() + sizes.tobytes() + np.array(list(runs), np.int64).tobytes() + tails


def decode_block(raw: bytes) -> tuple[list[bytes], np.ndarray]:
    n = int.from_bytes(raw[:4], "little")
    heads = np.frombuffer(raw, np.uint32, n, 4)
    sizes = np.frombuffer(raw, np.uint32, n, 4 + 4 * n)
    runs = np.frombuffer(raw, np.int64, n, 4 + 8 * n)
    at, last, keys = 4 + 16 * n, b"", []
    for s, tail in zip(heads.tolist(), (sizes - heads).tolist(), strict=True):
        last = last[:s] + raw[at : at + tail]
        at += tail
        keys.append(last)
    return keys, runs


def packed(rows: DataFrame, by: str, order: str, key: str, run: str) -> DataFrame:
    """``by, body``: the rows of each group, in order, as one front-coded block."""

    def one(group: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = pa.Table.from_batches(list(group)).sort_by(order)
        if t.num_rows:
            body = encode_block(t.column(key).cast(pa.binary()).to_pylist(), t.column(run).to_pylist())
            yield pa.RecordBatch.from_arrays([pa.array([t.column(by)[0].as_py()], pa.int64()), pa.array([body], pa.binary())], [by, "body"])

    return rows.select(by, order, key, run).groupBy(by).applyInArrow(one, f"{by} long, body binary")


def running(df: DataFrame, order: str, value: str, name: str, group: int = 1 << 16) -> DataFrame:
    """Adds the sum of ``value`` over rows before, by ``order`` (0, 1, 2, ..): sums of groups
    of rows first, so no window holds more than a group or the list of groups."""
    rows = df.withColumn("_g", F.floor(F.col(order) / group))
    sums = rows.groupBy("_g").agg(F.sum(value).alias("_n"))
    early = sums.select("_g", F.coalesce(F.sum("_n").over(Window.orderBy("_g").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_early"))
    inner = F.coalesce(F.sum(value).over(Window.partitionBy("_g").orderBy(order).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return rows.join(early, "_g").withColumn(name, F.col("_early") + inner).drop("_g", "_early")


def _assemble(counted: DataFrame, windows_of: DataFrame | None, length: int, block: int | None) -> WindowIndex:
    """Index over ``key, run``; ``windows_of`` are the places for the postings."""
    began = time.time()
    ranked = add_rank(counted, [F.col("key")])
    if block is None:
        n, size = ranked.agg(F.count("*"), F.coalesce(F.max(F.octet_length("key")), F.lit(0))).first()
        block = max(BLOCK, choose_block(n, size + 48, FENCE_MEMORY))
    runs = spool(ranked.select((F.col("rank") / block).cast("long").alias("block"), "rank", "key", "run"), "runs")
    fences = runs.groupBy("block").agg(F.min("key").alias("first_key"), F.sum("run").alias("n"), F.count("*").alias("entries"))
    fences = spool(running(fences, "block", "n", "before").select("block", "first_key", "entries", "n", "before"), "fences")
    count = fences.count()
    shard = max(SHARD_BLOCKS, -(-count // SHARDS))
    ends = fences.select("block", "before", "n").join(fences.select((F.col("block") - 1).alias("block"), F.col("first_key").cast("binary").alias("after")), "block", "left")
    rows = packed(runs, "block", "rank", "key", "run").join(ends, "block").withColumn("shard", F.floor(F.col("block") / shard))
    blocks = spool(rows.sortWithinPartitions("shard", "block"), "blocks", by=["shard"])
    postings = None
    if windows_of is not None:
        places = windows_of.join(runs.select("key", "block", "rank"), "key").select("block", "rank", "doc_id", "pos")
        postings = spool(places.repartitionByRange("rank").sortWithinPartitions("rank"), "postings")
    return WindowIndex(runs, blocks, fences, postings, length, block, shard, time.time() - began)


def build_index(corpus: DataFrame, length: int = WINDOW, block: int | None = None, with_postings: bool = True) -> WindowIndex:
    """Index of all windows; the block size follows the number of windows if not given."""
    rows = windows(corpus, length)
    return _assemble(compress_runs(rows), rows if with_postings else None, length, block)


def append_index(index: WindowIndex, corpus: DataFrame) -> WindowIndex:
    """Index with further documents: they are indexed on their own; lookups ask all parts."""
    own = build_index(corpus, index.length, index.block, index.postings is not None)
    return replace(index, deltas=(*index.deltas, own), held={})


def key_places(index: WindowIndex) -> DataFrame | None:
    """``doc_id, pos, key`` of all parts."""
    if index.postings is None:
        return None
    parts = [p.postings.join(p.runs.select("rank", "key"), "rank").select("doc_id", "pos", "key") for p in index.parts]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def compact_index(index: WindowIndex) -> WindowIndex:
    """One index of all parts: runs are added up key by key, blocks numbered anew."""
    if not index.deltas:
        return index
    both = index.runs.select("key", "run")
    for p in index.deltas:
        both = both.unionByName(p.runs.select("key", "run"))
    return _assemble(both.groupBy("key").agg(F.sum("run").alias("run")), key_places(index), index.length, index.block)


def file_bytes(df: DataFrame) -> int:
    """Bytes of the files under a written table."""
    spark, total = df.sparkSession, 0
    for f in df.inputFiles():
        p = spark._jvm.org.apache.hadoop.fs.Path(f)
        total += p.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(p).getLen()
    return total


def index_report(index: WindowIndex) -> dict[str, int]:
    """Bytes on disk of each part, and its rows; seconds of the build."""
    out = {"seconds": index.seconds}
    for name, df in (("runs", index.runs), ("blocks", index.blocks), ("fences", index.fences), ("postings", index.postings)):
        if df is not None:
            out[f"{name}_bytes"], out[f"{name}_rows"] = file_bytes(df), df.count()
    return out


def key_sizes(index: WindowIndex) -> DataFrame:
    """One row: bytes of all windows' keys plain, with equal windows counted (key and an
    8-byte count), and front-coded (shared length, length, count and rest) as stored."""
    size = F.octet_length("key").cast("long")
    plain = index.runs.agg(F.sum(size * F.col("run")).alias("plain"), F.sum(size + 8).alias("counted"), F.count("*").alias("keys"))
    return plain.join(F.broadcast(index.blocks.agg(F.sum(F.octet_length("body").cast("long") - 4).alias("coded"))))
