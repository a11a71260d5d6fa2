"""Soft search inside a task: queries walk down the sorted windows that the task holds.

Sorted windows are a tree: a node is a run of windows with equal first tokens.  A query
stands on nodes, each with the sum of costs so far, and goes on to the children that are
near its next token, by the shorter of the two lists; sums that fall below the threshold
end.  Only what occurs is ever stood on, so no candidates are written or sent: a task
answers with what it found.  Substitutions only.

For ``matched`` a task also finds the neighbours of the asked tokens among its own tokens, so
no table of neighbours is collected or sent, however many tokens are alike.  Queries are asked
in groups of ``TOKENS`` distinct tokens; a walk goes on in pieces of ``STEP`` children.
``grown`` is given its neighbours: they are packed in tasks, beside their queries, in groups of
about ``PAIRS``, and every segment meets every group.
"""

from __future__ import annotations

import ctypes
import math
import zlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ngramlake.functions.similarity import BASE
from ngramlake.functions.text import SEP
from ngramlake.operators import segments, vectors
from ngramlake.sources.tables import spool

TOKENS, STEP, PAIRS, AT_ONCE = 4096, 1 << 18, 1 << 20, 1 << 16
#: Names whose vectors and cosines are made at once.
NAMES = 512
LOW = (1 << 32) - 1


def groups(queries: DataFrame) -> list[dict]:
    """Queries (``query_id, tokens, m``) as numbers of their group's tokens."""
    t = queries.select("query_id", "tokens", "m").toArrow().combine_chunks()
    ids, m = t.column("query_id"), np.array(t.column("m").to_pylist(), np.int64)
    out, own, lo, tokens = [], {}, 0, t.column("tokens").to_pylist()

    def close(hi: int) -> None:
        slots = np.full((hi - lo, max(map(len, tokens[lo:hi]))), -1, np.int64)
        for k, words in enumerate(tokens[lo:hi]):
            slots[k, : len(words)] = [own[w] for w in words]
        out.append({"ids": pa.array(ids.slice(lo, hi - lo).to_pylist(), ids.type), "slots": slots, "m": m[lo:hi], "tokens": list(own)})

    for i, words in enumerate(tokens):
        if own and len(own.keys() | set(words)) > TOKENS:
            close(i)
            own, lo = {}, i
        for w in words:
            own.setdefault(w, len(own))
    if own:
        close(len(tokens))
    return out


def near_names(tokens: list[str], v: np.ndarray, buckets: np.ndarray, theta: float, base: float = BASE) -> tuple[np.ndarray, np.ndarray]:
    """Neighbours at ``theta`` among names of vectors ``v``: ``token << 32 | name's code`` in
    rising order, and costs.  Cosines are rounded as in ``vectors.neighbors``."""
    q, keys, a = vectors.word_vectors(tokens, buckets).T.copy(), [np.zeros(0, np.int64)], [np.zeros(0)]
    for lo in range(0, len(v), NAMES):
        c = v[lo : lo + NAMES] @ q
        i, j = np.nonzero(c >= theta - 1e-6)
        cos = np.round(c[i, j], 6)
        ok = cos >= theta
        keys.append((j[ok] << 32) | (i[ok] + lo + 1))
        a.append(base ** (1 - cos[ok]) - 1)
    key = np.concatenate(keys)
    keys.clear()
    order = np.argsort(key, kind="stable")
    key = key[order]
    cost = np.concatenate(a)
    a.clear()
    return key, cost[order]


def tree(columns: Iterable[np.ndarray], counts: list[np.ndarray] | None = None) -> list[np.ndarray]:
    """Nodes of each length of sorted windows, given as columns of codes (0: ended), as
    ``parent << 32 | code`` in rising order; the parents of the first are 0.  ``counts`` gets
    the windows of each node."""
    new, at, out = None, None, []
    for c in columns:
        differs = np.ones(len(c), bool)
        differs[1:] = c[1:] != c[:-1]
        new = differs if new is None else new | differs
        first = new & (c > 0)
        up = np.zeros(len(c), np.int64) if at is None else at
        out.append((up[first] << 32) | c[first])
        if counts is not None:
            starts = np.flatnonzero(new)
            counts.append(np.diff(np.append(starts, len(c)))[c[starts] > 0])
        at = np.cumsum(first) - 1  # of an ended window: some node, but it has no child
    return out


def _spread(lo: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each row ``lo .. lo + n``: the row's number and the places."""
    own = np.repeat(np.arange(len(n)), n)
    return own, np.arange(len(own)) - np.repeat(np.cumsum(n) - n, n) + lo[own]


def _meet(keys: np.ndarray, asked: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Which asked keys are there, and where."""
    if not len(keys):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    at = np.minimum(np.searchsorted(keys, asked), len(keys) - 1)
    there = np.flatnonzero(keys[at] == asked)
    return there, at[there]


def walk(group: dict, near: np.ndarray, a: np.ndarray, levels: list[np.ndarray], theta: float, base: float = BASE, hard: bool = False) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray]]:
    """For each length and piece: length, queries, their nodes there and sums of costs (``hard``:
    the greatest cost, costs being negative cosines)."""
    slots, m, low = group["slots"], group["m"], LOW

    def piece(part, keys, tok, node, q, s, lo, n, first, c):
        short = n[part] <= c[part]
        x, y = part[short], part[~short]
        own, at = _spread(lo[x], n[x])  # neighbours that are children
        ok, child = _meet(keys, (node[x[own]] << 32) | (near[at] & low))
        row, edge = x[own[ok]], at[ok]
        own, at = _spread(first[y], c[y])  # children that are neighbours
        ok, pair = _meet(near, (tok[y[own]] << 32) | (keys[at] & low))
        row, to, more = np.concatenate([row, y[own[ok]]]), np.concatenate([child, at[ok]]), a[np.concatenate([edge, pair])]
        sums = np.maximum(s[row], more) if hard else s[row] + more
        keep = np.round(-sums if hard else np.maximum(0.0, 1 - np.log1p(sums) / math.log(base)), 6) >= theta
        return q[row[keep]], to[keep], sums[keep]

    def go(j: int, q: np.ndarray, node: np.ndarray, s: np.ndarray):
        if j == len(levels) or not len(q):
            return
        keys, tok = levels[j], slots[q, j]
        lo, first = np.searchsorted(near, tok << 32), np.searchsorted(keys, node << 32)
        n, c = np.searchsorted(near, (tok + 1) << 32) - lo, np.searchsorted(keys, (node + 1) << 32) - first
        ends = np.cumsum(np.minimum(n, c))
        cut = np.unique(np.searchsorted(ends, np.arange(STEP, int(ends[-1]) + 1, STEP), "right"))
        for part in np.split(np.arange(len(q)), cut):
            who, to, sums = piece(part, keys, tok, node, q, s, lo, n, first, c)
            yield j + 1, who, to, sums
            more = m[who] > j + 1
            yield from go(j + 1, who[more], to[more], sums[more])

    try:
        yield from go(0, np.arange(len(m)), np.zeros(len(m), np.int64), np.full(len(m), -1.0 if hard else 0.0))
    finally:
        go = None  # it names itself, and would keep neighbours and nodes until a far collection


def window_columns(codes: np.ndarray, places: np.ndarray, most: int) -> Iterator[np.ndarray]:
    """The first ``most`` codes of the sorted windows, a column each; 0 from a document's end on."""
    padded, held = np.concatenate([codes, np.zeros(most, codes.dtype)]), np.ones(len(places), bool)
    for j in range(most):
        c = padded[places + j].astype(np.int64)
        held &= c > 0
        yield np.where(held, c, 0)


def give_back() -> None:
    """What a segment took is not kept by the worker: several share an executor."""
    pa.default_memory_pool().release_unused()
    if hasattr(c := ctypes.CDLL(None), "malloc_trim"):
        c.malloc_trim(0)


def _name_vectors(names: pa.Array, buckets: np.ndarray) -> np.ndarray:
    v, known = np.empty((len(names), buckets.shape[1])), {}
    for lo in range(0, len(names), NAMES):
        v[lo : lo + NAMES] = vectors.word_vectors(names.slice(lo, NAMES).to_pylist(), buckets, known)
    return v


def _matches(made: list[dict], buckets: np.ndarray, raw: dict, theta: float, base: float) -> Iterator[pa.RecordBatch]:
    """Queries that a segment's windows match; nothing of the segment outlives the call."""
    names, codes, places = segments.open_segment(raw)
    v = _name_vectors(names.cast(pa.string()).slice(0, len(names) if len(places) else 0), buckets)
    levels = tree(window_columns(codes, places, max(g["slots"].shape[1] for g in made)))
    del names, codes, places
    for g in made:
        found = np.zeros(len(g["m"]), bool)
        for n, q, _, _ in walk(g, *near_names(g["tokens"], v, buckets, theta, base), levels, theta, base):
            found[q[g["m"][q] == n]] = True
        yield pa.RecordBatch.from_arrays([g["ids"].filter(pa.array(found))], ["query_id"])


def matched(queries: DataFrame, theta: float, embeddings: DataFrame, index: segments.SegmentIndex, base: float = BASE) -> DataFrame:
    """``query_id`` of the queries that any window of the segments matches at ``theta``."""
    longest, made = index.length, groups(queries)
    if any(g["slots"].shape[1] > longest for g in made):
        raise ValueError(f"queries exceed the {longest} tokens that can be looked up")
    # the numbers of the table are of 32 bits; sums are of 64
    sent = queries.sparkSession.sparkContext.broadcast((made, vectors.bucket_matrix(embeddings).astype(np.float32)))

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        made, buckets = sent.value
        for b in batches:
            for i in range(b.num_rows):
                yield from _matches(made, buckets, {f: b.column(f)[i].as_py() for f in ("names", "codes", "places")}, theta, base)
                give_back()

    if not made:
        return queries.select("query_id").limit(0)
    kind = queries.schema["query_id"].dataType.simpleString()
    return index.rows.select("names", "codes", "places").mapInArrow(run, f"query_id {kind}").distinct()


GROUP = ["m", "slots", "nearby", "tok", "nb", "costs"]


def _near_group(asked: pa.Table, near: pa.Table) -> pa.Table:
    """Queries of a group as numbers of its tokens, and their neighbours by token and name."""
    toks, names = (pc.unique(near.column(c)).cast(pa.binary()) for c in ("tok", "nb"))
    names = names.take(pc.array_sort_indices(names))
    tok, nb = (pc.index_in(near.column(c).cast(pa.binary()), value_set=v).to_numpy().astype(np.int64) for c, v in (("tok", toks), ("nb", names)))
    key, a = (tok << 32) | nb, near.column("a").to_numpy()
    order = np.lexsort((a, key))
    key, a = key[order], a[order]
    new = np.concatenate([[True], key[1:] != key[:-1]])[: len(key)]
    key, a = key[new], a[new]
    words = asked.column("tokens").combine_chunks()
    m = asked.column("m").to_numpy().astype(np.int64)
    slots = np.full((len(m), int(m.max())), -1, np.int64)
    slots[np.arange(slots.shape[1])[None] < m[:, None]] = pc.fill_null(pc.index_in(words.flatten().cast(pa.binary()), value_set=toks), len(toks)).to_numpy(zero_copy_only=False)
    pack = zstandard.ZstdCompressor(level=3).compress
    body = [m.tobytes(), slots.tobytes(), pack(SEP.encode().join(names.to_pylist())), segments._shrink(key >> 32), segments._shrink(key & LOW), pack(a.tobytes())]
    ids = asked.column("query_id").combine_chunks()
    return pa.table([pa.ListArray.from_arrays(pa.array([0, len(ids)], pa.int32()), ids), *[pa.array([x], pa.binary()) for x in body]], names=["ids", *GROUP])


def near_groups(queries: DataFrame, near: DataFrame, pairs: int = PAIRS) -> DataFrame:
    """Queries (``query_id, tokens, m``) in groups, each with the neighbours ``tok, nb, a`` of its
    tokens; as many groups as make about ``pairs`` neighbours each."""
    queries = spool(queries.select("query_id", F.slice("tokens", F.lit(1), F.col("m")).alias("tokens"), "m").distinct(), "grown-queries")
    words = queries.select("query_id", F.explode(F.array_distinct("tokens")).alias("tok"))
    n = words.join(near.groupBy("tok").agg(F.count("*").alias("n")), "tok").agg(F.sum("n")).first()[0] or 0
    groups = max(1, -(-n // pairs))
    own = F.pmod(F.xxhash64("query_id"), F.lit(groups)).alias("_g")
    beside = words.select(own, "tok").distinct().join(near, "tok").select("_g", "tok", "nb", "a")
    both = queries.select(own, "*").groupBy("_g").cogroup(beside.groupBy("_g"))
    kind = queries.schema["query_id"].dataType.simpleString()
    made = spool(both.applyInArrow(_near_group, ", ".join([f"ids array<{kind}>", *[f"{x} binary" for x in GROUP]])), "grown-groups")
    return made.coalesce(-(-groups // 8))  # each task of the segments is one more for each of these


def _grow_segments(theta: float, base: float, hard: bool):
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, have, levels, counts, depth = None, None, [], [], 0
        unpack = zstandard.ZstdDecompressor().decompress
        for b in batches:
            for i in range(b.num_rows):
                raw = {f: b.column(f)[i].as_py() for f in ("names", "codes", "places", *GROUP)}
                m = np.frombuffer(raw["m"], np.int64)
                group = {"m": m, "slots": np.frombuffer(raw["slots"], np.int64).reshape(len(m), -1)}
                most, own = group["slots"].shape[1], (raw["names"], raw["codes"], raw["places"])
                if own != held or most > depth:
                    held = have = text = levels = None
                    names, codes, places = segments.open_segment(raw)
                    held, depth, counts = own, most, []
                    have, levels = names, tree(window_columns(codes, places, depth), counts)
                    text = names.cast(pa.string())
                    del codes, places
                nearby = pa.array(unpack(raw["nearby"]).split(SEP.encode()), pa.binary())
                code = pc.fill_null(pc.add(pc.index_in(nearby, value_set=have), 1), 0).to_numpy(zero_copy_only=False).astype(np.int64)
                nb = segments._grow(raw["nb"])
                there = np.flatnonzero(code[nb])
                near, a = (segments._grow(raw["tok"])[there] << 32) | code[nb[there]], np.frombuffer(unpack(raw["costs"]))[there]
                ids = b.column("ids")[i].values
                for n, q, node, s in walk(group, near, a, levels[:most], theta - 2e-6, base, hard):
                    whole = np.flatnonzero(m[q] == n)
                    for lo in range(0, len(whole), AT_ONCE):
                        at = whole[lo : lo + AT_ONCE]
                        yield _found(ids, q[at], n, node[at], s[at], levels, counts, text)
                raw = nearby = code = nb = there = near = a = None
                give_back()

    return run


def _found(ids: pa.Array, q: np.ndarray, n: int, node: np.ndarray, s: np.ndarray, levels: list[np.ndarray], counts: list[np.ndarray], text: pa.Array) -> pa.RecordBatch:
    words, at = [], node
    for j in range(n - 1, -1, -1):
        cell = levels[j][at]
        words.append(text.take(pa.array((cell & LOW) - 1)))
        at = cell >> 32
    key = pc.binary_join_element_wise(*words[::-1], SEP)
    parts = [ids.take(pa.array(q)), pa.array(q), pa.array(np.full(len(q), n, np.int32)), key, pa.array(s), pa.array(counts[n - 1][node].astype(np.int64))]
    return pa.RecordBatch.from_arrays(parts, ["query_id", "no", "m", "key", "s", "hits"])


def grown(queries: DataFrame, theta: float, near: DataFrame, index: segments.SegmentIndex, base: float = BASE, hard: bool = False, pairs: int = PAIRS) -> DataFrame:
    """``query_id, m, key, s, hits`` of all patterns that occur whose costs ``a`` of ``near``
    (``tok, nb, a``) keep their score at ``theta``, up to a margin that the caller decides."""
    kind = queries.schema["query_id"].dataType.simpleString()
    met = index.rows.select("names", "codes", "places").crossJoin(near_groups(queries, near, pairs))
    got = met.mapInArrow(_grow_segments(theta, base, hard), f"query_id {kind}, no long, m int, key string, s double, hits long")
    each = got.groupBy("query_id", "no", "m", "key").agg(F.min("s").alias("s"), F.sum("hits").alias("hits"))
    return each.groupBy("query_id", "m", "key").agg(F.min("s").alias("s"), F.max("hits").alias("hits"))


PART = "bucket int, names binary, cells binary"


def _parts(longest: int, buckets: int):
    """A segment's distinct windows, dealt by their first two tokens: their names and places in them."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                names, codes, places = segments.open_segment({f: b.column(f)[i].as_py() for f in ("names", "codes", "places")})
                text = names.to_pylist()
                sums = np.array([0, *map(zlib.crc32, text)], np.int64)
                padded, at = np.concatenate([codes, np.zeros(longest, codes.dtype)]).astype(np.int64), places.astype(np.int64)
                rows, held = np.zeros((len(at), longest), np.int64), np.ones(len(at), bool)
                for j in range(longest):
                    c = padded[at + j]
                    held &= c > 0  # a window ends with its document
                    rows[held, j] = c[held]
                rows = rows[np.concatenate([[True], (rows[1:] != rows[:-1]).any(1)])] if len(rows) else rows
                to = (sums[rows[:, 0]] * 31 + sums[rows[:, 1]]) % buckets
                order = np.argsort(to, kind="stable")
                cut = np.searchsorted(to[order], np.arange(buckets + 1))
                for k in np.flatnonzero(np.diff(cut)).tolist():
                    own, cells = np.unique(rows[order[cut[k] : cut[k + 1]]], return_inverse=True)
                    cells = cells.reshape(-1, longest) + (own[0] > 0)  # 0 stays 0
                    said = SEP.encode().join([text[c - 1] for c in own.tolist() if c])
                    yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), pa.array([zstandard.ZstdCompressor(level=3).compress(said)], pa.binary()), pa.array([segments._shrink(cells.T.ravel().astype(np.uint32))], pa.binary())], ["bucket", "names", "cells"])

    return run


def _totals(longest: int):
    """Distinct n-grams of two tokens and more, of the windows that came to a bucket."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list] = {}
        for b in batches:
            for k, said, cells in zip(*(b.column(i).to_pylist() for i in range(3)), strict=True):
                held.setdefault(k, []).append((zstandard.ZstdDecompressor().decompress(said).split(SEP.encode()), segments._grow(cells).reshape(longest, -1)))
        for k in list(held):
            parts, code = held.pop(k), {}
            rows = np.concatenate([np.array([0, *[code.setdefault(w, len(code) + 1) for w in names]], np.int64)[cells] for names, cells in parts], 1)
            rows = rows[:, np.lexsort(rows[::-1])]
            n = [len(x) for x in tree(rows)]
            yield pa.RecordBatch.from_arrays([pa.array(range(2, longest + 1), pa.int32()), pa.array(n[1:], pa.int64())], ["n", "types"])

    return run


def ngram_totals(index: segments.SegmentIndex, vocab: DataFrame, most: int) -> DataFrame:
    """``n, types``: distinct n-grams for n up to ``most``.  A segment's distinct windows of
    ``most`` tokens go to the bucket of their first two tokens, packed; shorter n-grams are
    their beginnings, so they are not sent."""
    spark = vocab.sparkSession
    buckets = max(int(spark.conf.get("spark.sql.shuffle.partitions", "200")), index.rows.count())
    parts = index.rows.select("names", "codes", "places").mapInArrow(_parts(most, buckets), PART).repartition(buckets, "bucket")
    more = parts.mapInArrow(_totals(most), "n int, types long").groupBy("n").agg(F.sum("types").alias("types"))
    return vocab.agg(F.lit(1).alias("n"), F.count("*").alias("types")).where("types > 0").unionByName(more.where("types > 0"))
