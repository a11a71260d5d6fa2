"""The window index in segments: one sorted window array for each run of documents.

A segment is one row: its distinct tokens in byte order, the tokens of its documents as
places in that list (0 ends each document), and all positions that hold a token, sorted by
the window that begins there.  Windows are read from the tokens, so a window costs its
position and its token once, not ten tokens, and nothing is shuffled.  A lookup asks every
segment by binary search: a pattern narrows a range of positions token by token.  Hits are
the ranges' sizes, places their positions; tokens beyond the sorted windows are compared
one by one.  Counts of all segments are summed, so every window of every document counts.

Asked patterns go to the segments in pieces of ``ASKED_BYTES`` at most.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ngramlake.functions.text import SEP
from ngramlake.operators.index import WINDOW
from ngramlake.sources.tables import spool

#: Tokens of a segment (a longer document is a segment of its own).
TOKENS = 1 << 20
#: Bytes of patterns sent to all segments at once; patterns in one row.
ASKED_BYTES, GROUP = 32 << 20, 200_000
ROW = "segment binary, names binary, docs binary, ends binary, codes binary, places binary"
FIELDS = ["names", "docs", "ends", "codes", "places"]


@dataclass
class SegmentIndex:
    rows: DataFrame
    length: int


def _shrink(x: np.ndarray) -> bytes:
    """Numbers byte place by byte place, compressed."""
    import zstandard

    planes = np.ascontiguousarray(x.view(np.uint8).reshape(-1, x.dtype.itemsize).T)
    return x.dtype.itemsize.to_bytes(1, "little") + zstandard.ZstdCompressor(level=3).compress(planes.tobytes())


def _grow(raw: bytes) -> np.ndarray:
    import zstandard

    planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(raw[1:]), np.uint8).reshape(raw[0], -1)
    return np.ascontiguousarray(planes.T).view(np.uint32 if raw[0] == 4 else np.int64).ravel()


def sort_windows(codes: np.ndarray, length: int) -> np.ndarray:
    """Positions that hold a token (not 0), by the ``length`` codes from there."""
    at = np.flatnonzero(codes)
    if not len(at):
        return at.astype(np.uint32)
    padded = np.concatenate([codes, np.zeros(length, codes.dtype)]).astype(np.int64)
    bits, rank, j = max(1, int(codes.max()).bit_length()), np.zeros(len(at), np.int64), 0
    while True:
        room = 63 - max(1, int(rank.max()).bit_length())
        key = rank
        while j < length and room >= bits:
            key, room, j = (key << bits) | padded[at + j], room - bits, j + 1
        order = np.argsort(key, kind="stable")
        if j == length:
            return at[order].astype(np.uint32)
        ranked = key[order]
        rank = np.empty(len(at), np.int64)
        rank[order] = np.cumsum(np.concatenate([[0], ranked[1:] != ranked[:-1]]))


def _segment(ids: pa.Array, tokens: pa.Array, length: int) -> pa.RecordBatch:
    import zstandard

    size = pc.fill_null(pc.list_value_length(tokens), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    flat = tokens.flatten().dictionary_encode()
    names = flat.dictionary.cast(pa.binary())
    order = pc.array_sort_indices(names).to_numpy()
    place = np.empty(len(order), np.uint32)
    place[order] = np.arange(1, len(order) + 1, dtype=np.uint32)
    codes = np.zeros(int(size.sum()) + len(size), np.uint32)
    held = np.ones(len(codes), bool)
    ends = np.cumsum(size + 1)
    held[ends - 1] = False
    codes[held] = place[flat.indices.to_numpy()]
    known = np.array([i is not None for i in ids.to_pylist()], np.int64)
    docs = np.concatenate([known, pc.fill_null(ids, 0).to_numpy(zero_copy_only=False).astype(np.int64)])
    text = zstandard.ZstdCompressor(level=3).compress(SEP.encode().join(names.take(pa.array(order)).to_pylist()))
    body = [text, _shrink(docs), _shrink(ends.astype(np.int64)), _shrink(codes), _shrink(sort_windows(codes, length))]
    return pa.RecordBatch.from_arrays([pa.array([b""], pa.binary()), *[pa.array([x], pa.binary()) for x in body]], ["segment", *FIELDS])


def build_segments(corpus: DataFrame, length: int = WINDOW, most: int = TOKENS) -> SegmentIndex:
    """Segments over ``doc_id, tokens``."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        n = 0
        for b in batches:
            size = pc.fill_null(pc.list_value_length(b.column(1)), 0).to_numpy(zero_copy_only=False).astype(np.int64)
            upto, lo = np.cumsum(size), 0
            while lo < b.num_rows:
                early = int(upto[lo - 1]) if lo else 0
                hi = max(int(np.searchsorted(upto, early + most - n, "right")), lo if held else lo + 1)
                if hi > lo:
                    held.append(b.slice(lo, hi - lo))
                    n += int(upto[hi - 1]) - early
                if hi < b.num_rows:
                    t = pa.Table.from_batches(held).combine_chunks()
                    yield _segment(t.column(0).chunk(0), t.column(1).chunk(0), length)
                    held, n = [], 0
                lo = hi
        if held:
            t = pa.Table.from_batches(held).combine_chunks()
            yield _segment(t.column(0).chunk(0), t.column(1).chunk(0), length)

    made = corpus.select(F.col("doc_id").cast("long"), "tokens").mapInArrow(run, ROW)
    return SegmentIndex(spool(made.drop("segment"), "segments"), length)


def open_segment(raw: dict) -> tuple[pa.Array, np.ndarray, np.ndarray]:
    """Names in byte order, codes and sorted positions of a segment."""
    import zstandard

    names = pa.array(zstandard.ZstdDecompressor().decompress(raw["names"]).split(SEP.encode()), pa.binary())
    return names, _grow(raw["codes"]), _grow(raw["places"])


def _words(keys: pa.Array, names: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Patterns as rows of codes (-1: not in the segment; 0 after their end) and their lengths."""
    split = pc.split_pattern(keys, SEP)
    size = pc.list_value_length(split).to_numpy(zero_copy_only=False).astype(np.int64)
    flat = split.flatten().dictionary_encode()
    found = pc.fill_null(pc.add(pc.index_in(flat.dictionary.cast(pa.binary()), value_set=names), 1), -1).to_numpy(zero_copy_only=False)[flat.indices.to_numpy()]
    out = np.zeros((len(keys), int(size.max()) if len(size) else 0), np.int64)
    out[np.arange(out.shape[1])[None] < size[:, None]] = found
    return out, size


def _bound(read, lo: np.ndarray, hi: np.ndarray, want: np.ndarray, right: bool) -> np.ndarray:
    """Least place of ``lo .. hi`` whose code is not below (``right``: above) the wanted one."""
    lo, hi = lo.copy(), hi.copy()
    todo = np.flatnonzero(lo < hi)
    while len(todo):
        mid = (lo[todo] + hi[todo]) >> 1
        low = read(mid) <= want[todo] if right else read(mid) < want[todo]
        lo[todo[low]], hi[todo[~low]] = mid[low] + 1, mid[~low]
        todo = todo[lo[todo] < hi[todo]]
    return lo


def _ranges(codes: np.ndarray, places: np.ndarray, words: np.ndarray, size: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Patterns that occur by their first ``length`` tokens: numbers and ranges of places."""
    live = np.flatnonzero(((words >= 0).all(1)) & (size > 0))
    first = np.concatenate([[0], np.cumsum(np.bincount(codes[codes > 0], minlength=int(words.max(initial=0)) + 1))])
    lo, hi = first[words[live, 0]], first[words[live, 0] + 1]
    padded = np.concatenate([codes, np.zeros(length, codes.dtype)]).astype(np.int64)
    for j in range(1, min(words.shape[1], length)):
        more = np.flatnonzero((size[live] > j) & (lo < hi))
        read, want = (lambda at, j=j: padded[places[at] + j]), words[live[more], j]
        left, end = _bound(read, lo[more], hi[more], want, False), hi[more]
        there = np.flatnonzero(left < end)
        there = there[read(left[there]) == want[there]]
        right = left.copy()  # only what is there has an upper end to look for
        right[there] = _bound(read, left[there] + 1, end[there], want[there], True)
        lo[more], hi[more] = left, right
    keep = lo < hi
    return live[keep], lo[keep], hi[keep]


def _tails(codes: np.ndarray, at: np.ndarray, words: np.ndarray, size: np.ndarray, length: int) -> np.ndarray:
    """Which positions go on as their patterns do beyond the sorted windows."""
    ok = np.ones(len(at), bool)
    padded = np.concatenate([codes, np.zeros(words.shape[1], codes.dtype)])
    for j in range(length, words.shape[1]):
        ok &= (size <= j) | (padded[at + j] == words[:, j])
    return ok


def _search(length: int, whole: bool):
    """Answers each segment's patterns: ``key, hits``, or with ``whole`` ``key, doc_id, pos``."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                raw = {f: b.column(f)[i].as_py() for f in FIELDS}
                keys = b.column("asked")[i].values
                names, codes, places = open_segment(raw)
                words, size = _words(keys, names)
                who, lo, hi = _ranges(codes, places, words, size, length)
                n = hi - lo
                take = np.flatnonzero((size[who] > length) | whole)
                own = np.repeat(take, n[take])
                at = places[np.arange(len(own)) - np.repeat(np.cumsum(n[take]) - n[take], n[take]) + np.repeat(lo[take], n[take])].astype(np.int64)
                ok = _tails(codes, at, words[who[own]], size[who[own]], length)
                own, at = own[ok], at[ok]
                n[take] = np.bincount(own, minlength=len(who))[take]
                if whole:
                    docs, ends = _grow(raw["docs"]), _grow(raw["ends"])
                    doc = np.searchsorted(ends, at, "right")
                    known, ids = docs[: len(ends)][doc], docs[len(ends) :][doc]
                    starts = np.concatenate([[0], ends[:-1]])
                    got = [keys.take(pa.array(who[own])), pa.array(ids, mask=known == 0), pa.array((at - starts[doc]).astype(np.int32))]
                    yield pa.RecordBatch.from_arrays(got, ["key", "doc_id", "pos"])
                else:
                    yield pa.RecordBatch.from_arrays([keys.take(pa.array(who[n > 0])), pa.array(n[n > 0].astype(np.int64))], ["key", "hits"])

    return run


def _asked(patterns: DataFrame) -> DataFrame:
    return spool(patterns.select("key").where(F.col("key") != "").distinct(), "asked")


def _answers(keys: DataFrame, index: SegmentIndex, whole: bool, kind: str) -> DataFrame:
    n, size = keys.agg(F.count("*"), F.coalesce(F.sum(F.octet_length("key").cast("long") + 8), F.lit(0))).first()
    pieces = max(1, -(-size // ASKED_BYTES))  # sorted: neighbours take the same way through the places
    rows = max(1, -(-n // GROUP // pieces))
    h, out = F.xxhash64("key"), None
    for k in range(pieces):
        part = keys.where(F.pmod(h, F.lit(pieces)) == k).groupBy(F.pmod(F.shiftright(h, 20), F.lit(rows)).alias("_g")).agg(F.sort_array(F.collect_list("key")).alias("asked"))
        met = index.rows.crossJoin(F.broadcast(part.select("asked"))).select(*FIELDS, "asked")
        got = met.mapInArrow(_search(index.length, whole), kind)
        out = got if out is None else out.unionByName(got)
    return out


def hits(patterns: DataFrame, index: SegmentIndex) -> DataFrame:
    """``key, hits`` for each distinct non-empty pattern that occurs, of any length."""
    return _answers(_asked(patterns), index, False, "key string, hits long").groupBy("key").agg(F.sum("hits").alias("hits"))


def all_hits(patterns: DataFrame, index: SegmentIndex) -> DataFrame:
    """``key, hits`` for each distinct non-empty pattern, 0 for those that do not occur."""
    keys = _asked(patterns)
    found = _answers(keys, index, False, "key string, hits long").unionByName(keys.withColumn("hits", F.lit(0).cast("long")))
    return found.groupBy("key").agg(F.sum("hits").alias("hits"))


def occurrences(patterns: DataFrame, index: SegmentIndex) -> DataFrame:
    """``key, doc_id, pos`` of every occurrence."""
    return _answers(_asked(patterns), index, True, "key string, doc_id long, pos int")
