"""Scans without an index: substrings, several patterns at once, k errors, expressions."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ngramlake.functions.text import SEP
from ngramlake.operators.vocab import ngrams


def scan_exact(docs: DataFrame, patterns: DataFrame, corpus: DataFrame, longest: int) -> DataFrame:
    """``key, hits`` of token patterns: windows of each length against the broadcast set."""
    p = patterns.select("key").distinct().withColumn("n", F.size(F.split("key", SEP)))
    out = None
    for n in range(1, longest + 1):
        part = ngrams(corpus, n).join(F.broadcast(p.where(F.col("n") == n).select("key")), "key", "left_semi").groupBy("key").agg(F.count("*").alias("hits"))
        out = part if out is None else out.unionByName(part)
    return p.select("key").join(out, "key", "left").select("key", F.coalesce("hits", F.lit(0)).alias("hits"))


def scan_contains(docs: DataFrame, patterns: DataFrame, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """``item_id, doc_id`` where a document's text holds an item's text; few patterns, broadcast."""
    return docs.select(id_col, text).join(F.broadcast(patterns), F.contains(F.col(text), F.col("pattern"))).select("item_id", id_col)


def scan_regex(docs: DataFrame, expression: str, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    return docs.select(id_col, F.regexp_count(F.col(text), F.lit(expression)).alias("n")).where("n > 0")


@F.pandas_udf(T.IntegerType())
def k_error_distance(text: pd.Series, pattern: pd.Series) -> pd.Series:
    """Least edit distance of a pattern to any substring of a text, one machine word at a
    time: a column of the distance matrix as two bit vectors (any length, Python integers)."""

    def best(t: str, p: str) -> int:
        m = len(p)
        if not m:
            return 0
        where: dict[str, int] = {}
        for i, c in enumerate(p):
            where[c] = where.get(c, 0) | 1 << i
        mask, top = (1 << m) - 1, 1 << (m - 1)
        up, down, score, low = mask, 0, m, m
        for c in t:
            eq = where.get(c, 0)
            x = (((eq & up) + up) ^ up) | eq | down
            plus, minus = down | (~(x | up) & mask), up & x
            score += 1 if plus & top else -1 if minus & top else 0
            low = min(low, score)
            plus, minus = (plus << 1) & mask, (minus << 1) & mask
            up, down = minus | (~((eq | down) | plus) & mask), plus & (eq | down)
        return low

    return pd.Series([best(a or "", b or "") for a, b in zip(text, pattern, strict=True)])


class PatternBlock:
    """Patterns laid end to end in one bit vector, a spare bit after each so that no carry
    passes on: a character of a text moves the distance columns of all of them at once."""

    STEPS = 512

    def __init__(self, patterns: list[str]):
        self.sizes = np.array([len(p) for p in patterns], np.int64)
        self.where: dict[str, int] = {}
        self.mask, at, tops = 0, 0, []
        for p in patterns:
            for i, c in enumerate(p):
                self.where[c] = self.where.get(c, 0) | 1 << at + i
            self.mask |= ((1 << len(p)) - 1) << at
            if p:
                tops.append(at + len(p) - 1)
            at += len(p) + 1
        self.width = max(1, -(-at // 8))
        self.some = np.flatnonzero(self.sizes)
        self.byte, self.bit = np.array(tops, np.int64) // 8, (np.array(tops, np.int64) % 8).astype(np.uint8)

    def _moves(self, columns: list[bytes]) -> np.ndarray:
        rows = np.frombuffer(b"".join(columns), np.uint8).reshape(len(columns), self.width)
        return (rows[:, self.byte] >> self.bit & 1).astype(np.int32)

    def distances(self, text: str) -> np.ndarray:
        """Least edit distance of each pattern to any substring of ``text``."""
        low, mask, width, where = self.sizes.copy(), self.mask, self.width, self.where
        score, up, down = self.sizes[self.some], mask, 0
        for at in range(0, len(text) if len(self.some) else 0, self.STEPS):
            more, less = [], []
            for c in text[at : at + self.STEPS]:
                eq = where.get(c, 0)
                x = ((((eq & up) + up) ^ up) | eq | down) & mask
                plus, minus = down | (mask & ~(x | up)), up & x
                more.append(plus.to_bytes(width, "little"))
                less.append(minus.to_bytes(width, "little"))
                plus, minus = (plus << 1) & mask, (minus << 1) & mask
                up, down = minus | (mask & ~(eq | down | plus)), plus & (eq | down)
            steps = score + np.cumsum(self._moves(more) - self._moves(less), axis=0)
            low[self.some] = np.minimum(low[self.some], steps.min(axis=0))
            score = steps[-1]
        return low


def scan_k_errors(docs: DataFrame, patterns: DataFrame, id_col: str = "doc_id", text: str = "text", block: int = 1 << 18) -> DataFrame:
    """``item_id, doc_id, distance`` of every pattern to every text; patterns (``item_id,
    pattern``) are read in blocks of about ``block`` characters, one pass over the texts each.

    Null texts and patterns count as empty; an empty pattern is at distance 0."""

    def scan(items: list, found: list[str]):
        def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            own, names = PatternBlock(found), pa.array(items, item_type)
            for b in batches:
                for k in range(b.num_rows):
                    got = own.distances(b.column(1)[k].as_py() or "")
                    yield pa.RecordBatch.from_arrays([names, b.column(0).take(pa.array([k] * len(names))), pa.array(got, pa.int32())], ["item_id", id_col, "distance"])

        return rows.mapInArrow(run, T.StructType([T.StructField("item_id", kind), T.StructField(id_col, docs.schema[id_col].dataType), T.StructField("distance", T.IntegerType())]))

    rows, kind = docs.select(id_col, text), patterns.schema["item_id"].dataType
    item_type = {"bigint": pa.int64(), "int": pa.int32()}.get(kind.simpleString(), pa.string())
    out, items, found, size = None, [], [], 0
    for r in patterns.select("item_id", "pattern").toLocalIterator():
        items.append(r[0])
        found.append(r[1] or "")
        size += len(found[-1]) + 1
        if size >= block:
            part, items, found, size = scan(items, found), [], [], 0
            out = part if out is None else out.unionByName(part)
    if items or out is None:
        part = scan(items, found)
        out = part if out is None else out.unionByName(part)
    return out


def scan_levenshtein(left: DataFrame, right: DataFrame, a: str, b: str, k: int) -> DataFrame:
    """Pairs within ``k`` edits; lengths first, both sides by their own length buckets."""
    x = left.withColumn("_n", F.explode(F.sequence(F.length(a) - k, F.length(a) + k)))
    y = right.withColumn("_n", F.length(b))
    return x.join(y, "_n").withColumn("distance", F.levenshtein(F.col(a), F.col(b), k)).where(F.col("distance") >= 0).drop("_n")
