"""Exact lookup of token patterns in the sorted window array.

Each pattern is a range of keys.  Its ends are placed among the fences in memory (beyond
``FENCE_BYTES`` among packed groups of fences, by a join), gathered by block, and joined
with the blocks they fall into: one row a block, read once however many patterns ask it,
from the folders of the touched shards only.  Whether a pattern occurs takes its lower end
alone: the first key not below it begins with it or none does.  Counts and places take
both ends.  Patterns longer than the index's windows are refused; ``long_lookup`` verifies
those.
"""

from __future__ import annotations

from bisect import bisect_left, bisect_right
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ngramlake.functions.text import AFTER, SEP, key_size
from ngramlake.operators.index import WindowIndex, decode_block, packed
from ngramlake.sources.tables import spool

FENCE_BYTES = 256 << 20
COARSE = 4096
#: Patterns that meet one copy of a block in one row; a crowded block takes several rows.
GROUP = 200_000
#: Bytes of asked keys below which they go to the blocks' tasks, and the blocks stay.
ASKED_BYTES = 64 << 20


def fence_bytes(index: WindowIndex) -> int:
    if "bytes" not in index.held:
        index.held["bytes"] = index.fences.agg(F.coalesce(F.sum(F.octet_length("first_key") + 48), F.lit(0))).first()[0]
    return index.held["bytes"]


def _keys(df: DataFrame, index: WindowIndex, name: str) -> object:
    """Sorted first keys on every executor."""
    if name not in index.held:
        index.held[name] = index.spark.sparkContext.broadcast([r[0].encode() for r in df.orderBy("block").select("first_key").collect()])
    return index.held[name]


def _units(fences, length: int):
    """Unit (block or group of blocks) of each end: the last one whose first key is not above it."""
    sep, after = SEP.encode(), AFTER.encode()

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        first = fences.value
        for b in batches:
            keys, signs = b.column(0).cast(pa.binary()).to_pylist(), b.column(1).to_pylist()
            for k in keys:
                if k.count(sep) >= length:
                    raise ValueError(f"a pattern of over {length} tokens is longer than the index's windows; use long_lookup")
            at = [max(0, bisect_right(first, k if s < 0 else k + after) - 1) for k, s in zip(keys, signs, strict=True)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(at, pa.int64())], ["key", "sign", "unit"])

    return run


def _meet(items: DataFrame, unit: str, fields: list[str], table: DataFrame, index: WindowIndex | None = None) -> DataFrame:
    """``items`` gathered by ``unit`` beside their rows of ``table``: crowded units in several
    rows, and of an index's blocks only the shards that are asked."""
    items = spool(items, "asked")
    shard = F.floor(F.col(unit) / (index.shard if index else 1 << 62))
    n, size, shards = items.agg(F.count("*"), F.sum(F.octet_length("key").cast("long") + 24), F.collect_set(shard)).first()
    part = F.pmod(F.xxhash64("key"), F.lit(max(1, -(-n // GROUP))))
    asked = items.groupBy(unit, part.alias("_part")).agg(*[F.collect_list(f).alias(f) for f in fields]).drop("_part")
    if index:
        table = table.where(F.col("shard").isin(shards))
    return table.join(F.broadcast(asked) if (size or 0) <= ASKED_BYTES else asked, unit)


def place(ends: DataFrame, index: WindowIndex, memory: int = FENCE_BYTES) -> DataFrame:
    """``key, sign, block`` of ends ``key, sign`` (-1: the key, 1: after all that begin with it)."""
    ends = ends.select("key", "sign")
    if fence_bytes(index) <= memory:
        rows = ends.mapInArrow(_units(_keys(index.fences, index, "fences"), index.length), "key string, sign int, unit long")
        return rows.withColumnRenamed("unit", "block")
    if "groups" not in index.held:
        grouped = index.fences.withColumn("unit", F.floor(F.col("block") / COARSE))
        index.held["groups"] = spool(packed(grouped, "unit", "block", "first_key", "entries"), "fence-groups")
    top = _keys(index.fences.where(F.col("block") % COARSE == 0), index, "coarse")
    rows = ends.mapInArrow(_units(top, index.length), "key string, sign int, unit long")
    after = AFTER.encode()

    def fine(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for unit, body, keys, signs in zip(*(c.to_pylist() for c in b.columns), strict=True):
                first, _ = decode_block(body)
                at = [unit * COARSE + max(0, bisect_right(first, k.encode() + after * (s > 0)) - 1) for k, s in zip(keys, signs, strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(keys), pa.array(signs, pa.int32()), pa.array(at, pa.int64())], ["key", "sign", "block"])

    met = _meet(rows, "unit", ["key", "sign"], index.held["groups"])
    return met.select("unit", "body", "key", "sign").mapInArrow(fine, "key string, sign int, block long")


def _asked(patterns: DataFrame) -> DataFrame:
    return patterns.select("key").where(F.col("key") != "").distinct()


def exists(patterns: DataFrame, index: WindowIndex, memory: int = FENCE_BYTES) -> DataFrame:
    """``key`` of the distinct patterns that occur: one end, one block each."""
    sep = SEP.encode()

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for body, after, asked in zip(*(c.to_pylist() for c in b.columns), strict=True):
                have, _ = decode_block(body)
                have.append(after or b"")
                found = []
                for k in asked:
                    raw = k.encode()
                    at = have[bisect_left(have, raw, 0, len(have) - 1)]
                    if at.startswith(raw) and (len(at) == len(raw) or at[len(raw) : len(raw) + 1] == sep):
                        found.append(k)
                yield pa.RecordBatch.from_arrays([pa.array(found, pa.string())], ["key"])

    keys, out = _asked(patterns), None
    for part in index.parts:
        met = _meet(place(keys.withColumn("sign", F.lit(-1)), part, memory), "block", ["key"], part.blocks, part)
        found = met.select("body", "after", "key").mapInArrow(run, "key string")
        out = found if out is None else out.unionByName(found)
    return out.distinct() if index.deltas else out


def _bounds(keys: DataFrame, index: WindowIndex, memory: int) -> DataFrame:
    """``key, hits, lo, hi`` of distinct keys in one part: windows counted, range of ranks."""
    block, after = index.block, AFTER.encode()

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for unit, body, before, asked, signs in zip(*(c.to_pylist() for c in b.columns), strict=True):
                have, runs = decode_block(body)
                upto = np.concatenate([[0], np.cumsum(runs)])
                at = np.array([bisect_left(have, k.encode() + after * (s > 0)) for k, s in zip(asked, signs, strict=True)], np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(asked, pa.string()), pa.array(signs, pa.int32()), pa.array(before + upto[at], pa.int64()), pa.array(unit * block + at)], ["key", "sign", "n", "rank"])

    ends = keys.select("key", F.explode(F.array(F.lit(-1), F.lit(1))).alias("sign"))
    met = _meet(place(ends, index, memory), "block", ["key", "sign"], index.blocks, index)
    got = met.select("block", "body", "before", "key", "sign").mapInArrow(run, "key string, sign int, n long, rank long")
    return got.groupBy("key").agg(F.sum(F.col("sign") * F.col("n")).alias("hits"), F.max(F.when(F.col("sign") < 0, F.col("rank"))).alias("lo"), F.max(F.when(F.col("sign") > 0, F.col("rank"))).alias("hi"))


def exact_lookup(patterns: DataFrame, index: WindowIndex, memory: int = FENCE_BYTES) -> DataFrame:
    """``key, hits`` for each distinct non-empty ``key`` of at most the window's length."""
    keys = _asked(patterns)
    out = keys.withColumn("hits", F.lit(0).cast("long"))
    for part in index.parts:
        out = out.unionByName(_bounds(keys, part, memory).select("key", "hits"))
    return out.groupBy("key").agg(F.sum("hits").alias("hits"))


def exact_lookup_sql(patterns: DataFrame, index: WindowIndex) -> DataFrame:
    """The same without Python: windows cut to each pattern length that is asked for."""
    keys = patterns.select("key").where(F.col("key") != "").distinct().withColumn("n", key_size(F.col("key")))
    sizes = keys.groupBy().agg(F.sort_array(F.collect_set("n")).alias("sizes"))  # one row, at most a window's length
    runs = index.runs.select("key", "run")
    for part in index.deltas:
        runs = runs.unionByName(part.runs.select("key", "run"))
    heads = runs.join(F.broadcast(sizes)).select("key", "run", F.explode("sizes").alias("n")).where(key_size(F.col("key")) >= F.col("n"))
    heads = heads.select("n", F.call_function("substring_index", F.col("key"), F.lit(SEP), F.col("n")).alias("key"), "run")
    found = heads.join(keys, ["n", "key"], "left_semi").groupBy("key").agg(F.sum("run").alias("hits"))
    return keys.select("key").join(found, "key", "left").select("key", F.coalesce("hits", F.lit(0)).cast("long").alias("hits"))


def begins(key: Column, pattern: Column) -> Column:
    return (key == pattern) | F.startswith(key, F.concat(pattern, F.lit(SEP)))


def _by_block(keys: DataFrame, index: WindowIndex) -> DataFrame:
    """``key, lo, hi, block``: a row for each block of a pattern's range."""
    got = _bounds(keys, index, FENCE_BYTES).where("hi > lo")
    at = F.sequence(F.floor(F.col("lo") / index.block), F.floor((F.col("hi") - 1) / index.block))
    return got.select("key", "lo", "hi", F.explode(at).alias("block"))


def matching_windows(patterns: DataFrame, index: WindowIndex) -> DataFrame:
    """``key, window, run``: the index rows of each pattern's range, block by block."""
    keys, out = _asked(patterns), None
    for part in index.parts:
        block = part.block

        def run(batches: Iterable[pa.RecordBatch], block: int = block) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for unit, body, asked, los, his in zip(*(c.to_pylist() for c in b.columns), strict=True):
                    have, runs = decode_block(body)
                    for k, lo, hi in zip(asked, los, his, strict=True):
                        s = slice(max(0, lo - unit * block), min(len(have), hi - unit * block))
                        own = have[s]
                        yield pa.RecordBatch.from_arrays([pa.array([k] * len(own), pa.string()), pa.array(own, pa.binary()).cast(pa.string()), pa.array(runs[s], pa.int64())], ["key", "window", "run"])

        met = _meet(_by_block(keys, part), "block", ["key", "lo", "hi"], part.blocks, part)
        got = met.select("block", "body", "key", "lo", "hi").mapInArrow(run, "key string, window string, run long")
        out = got if out is None else out.unionByName(got)
    return out.groupBy("key", "window").agg(F.sum("run").alias("run")) if index.deltas else out


def occurrences(patterns: DataFrame, index: WindowIndex) -> DataFrame:
    """``key, doc_id, pos`` of every occurrence: the postings of each pattern's ranks."""
    keys, out = _asked(patterns), None
    for part in index.parts:
        own = _by_block(keys, part).join(part.postings, "block").where((F.col("rank") >= F.col("lo")) & (F.col("rank") < F.col("hi"))).select("key", "doc_id", "pos")
        out = own if out is None else out.unionByName(own)
    return out


def long_lookup(patterns: DataFrame, index: WindowIndex, corpus: DataFrame) -> DataFrame:
    """``key, hits`` of patterns of any length: heads are looked up, the rest is verified."""
    p = patterns.select("key").distinct().withColumn("t", F.split("key", SEP)).withColumn("head", F.array_join(F.slice("t", 1, index.length), SEP))
    at = occurrences(p.select(F.col("head").alias("key")), index).withColumnRenamed("key", "head")
    full = at.join(p, "head").join(corpus.select("doc_id", "tokens"), "doc_id")
    ok = F.array_join(F.slice("tokens", F.col("pos") + 1, F.size("t")), SEP) == F.col("key")
    hits = full.where(ok).groupBy("key").agg(F.count("*").alias("hits"))
    return p.select("key").join(hits, "key", "left").select("key", F.coalesce("hits", F.lit(0)).alias("hits"))
