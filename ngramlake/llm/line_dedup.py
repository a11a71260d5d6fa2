"""Line dedup: a segment-partition edit join over the distinct lines of a corpus.

Lines of at least ``least`` bytes are compared (by bytes, at most ``edits``
edits); the first occurrence of each class - least document id, then place - is
kept, the others are removed.  Shorter lines take no part in the edit join: from
``exact`` bytes on they are compared for equality, below it always kept.

*Candidates.*  A line is cut into ``edits + 1`` segments, its index keys (length,
segment, bytes).  For each length not above its own and each segment, a line
probes the substrings that could hold that segment if it is the one left whole:
the shifts that the edits before and after it allow.  Keys travel as sorted runs
of hashes, one run for each task and range, so equal lines of a task travel once;
a range is intersected in one task, whose size is that of the range.  A line's name
holds a sketch of its bytes; pairs whose sketches differ in more bits than the
edits can flip never leave that task, so a family of lines that share a segment
but differ elsewhere does not become a table of pairs.

*Verification.*  Only candidates' texts are fetched: all lines of the names that meet,
so lines whose short names clash are told apart by their texts.  Common ends are cut off
and the rest goes through a bit-parallel edit distance in a band that gives up as soon
as the bound cannot be met.  Links between full (128-bit) names close to classes by label
spreading.

Cases: null text gives no lines and stays null; empty lines are kept; equal lines
need no edit join; a document is known by its id and its text's hash, so rows that share
an id (or have none) are documents of their own, in order of id, hash and place, and only
equal rows are one; null ids stand before all others; an empty table gives no rows; further columns are kept
as they are.  No cap: lines that
share a segment and length are all compared.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import n_buckets, spool, unused
from .near_dedup import components

EDITS, LEAST, NO_ID = 2, 24, -(1 << 63)
RUNS = "bucket int, kind int, a binary, b binary, c binary, d binary, e binary"
_RUN_TYPES = [pa.int32(), pa.int32()] + [pa.binary()] * 5
_RUN_NAMES = [f.split()[0] for f in RUNS.split(", ")]


def segments(n: int, parts: int) -> list[tuple[int, int]]:
    """Even cuts of ``n``: (start, length); the longer ones come last."""
    short, longer = n // parts, n % parts
    out, at = [], 0
    for i in range(parts):
        size = short + (i >= parts - longer)
        out.append((at, size))
        at += size
    return out


def probes(n: int, edits: int = EDITS) -> list[tuple[int, int, int, int]]:
    """(length, segment, start, size) of the substrings that a line of ``n`` looks up.

    With segment ``i`` whole, at most ``i`` edits lie before it or at most
    ``edits - i`` after it; its shift is bounded by both.
    """
    out = []
    for length in range(max(0, n - edits), n + 1):
        delta = n - length
        for i, (at, size) in enumerate(segments(length, edits + 1)):
            lo = max(at - i, at + delta - (edits - i))
            hi = min(at + i, at + delta + (edits - i))
            out += [(length, i, s, size) for s in range(max(lo, 0), min(hi, n - size) + 1)]
    return out


def line_keys(line: bytes, plans: dict, edits: int = EDITS) -> tuple[list[int], list[int]]:
    """Index and probe keys of one line."""
    from xxhash import xxh3_64_intdigest as h

    n = len(line)
    if n not in plans:
        if len(plans) > 20_000:
            plans.clear()
        plans[n] = [(at, at + size, n * 8 + i) for i, (at, size) in enumerate(segments(n, edits + 1))], [(s, s + size, length * 8 + i) for length, i, s, size in probes(n, edits)]
    own, look = plans[n]
    return [h(line[s:e], seed) for s, e, seed in own], [h(line[s:e], seed) for s, e, seed in look]


def within(a: bytes, b: bytes, edits: int = EDITS) -> bool:
    """Whether at most ``edits`` edits lie between two lines."""
    if abs(len(a) - len(b)) > edits:
        return False
    n = min(len(a), len(b))
    start, step = 0, n
    while step:  # longest common prefix by halving
        while start + step <= n and a[start : start + step] == b[start : start + step]:
            start += step
        step //= 2
    a, b = a[start:], b[start:]
    n, end, step = min(len(a), len(b)), 0, min(len(a), len(b))
    while step:
        while end + step <= n and a[len(a) - end - step : len(a) - end] == b[len(b) - end - step : len(b) - end]:
            end += step
        step //= 2
    a, b = a[: len(a) - end], b[: len(b) - end]
    if not a or not b:
        return max(len(a), len(b)) <= edits
    if len(a) > len(b):
        a, b = b, a
    # columns of b against a, one bit for each character of a
    where: dict[int, int] = {}
    for i, c in enumerate(a):
        where[c] = where.get(c, 0) | 1 << i
    m = len(a)
    mask, top, score = (1 << m) - 1, 1 << (m - 1), m
    up, down = mask, 0
    for j, c in enumerate(b):
        eq = where.get(c, 0)
        x = (((eq & up) + up) ^ up) | eq | down
        plus, minus = down | (~(x | up) & mask), up & x
        if plus & top:
            score += 1
        elif minus & top:
            score -= 1
        if score > edits + len(b) - j - 1:
            return False
        plus, minus = ((plus << 1) | 1) & mask, (minus << 1) & mask
        up, down = minus | (~((eq | down) | plus) & mask), plus & (eq | down)
    return score <= edits


def sketches(lines: list[bytes]) -> np.ndarray:
    """32 parity bits of each line's bytes by their low five bits: an edit flips at most two."""
    sizes = np.fromiter(map(len, lines), np.int64, len(lines))
    bits = np.left_shift(np.uint32(1), np.frombuffer(b"".join(lines), np.uint8).astype(np.uint32) & np.uint32(31), dtype=np.uint32)
    return np.bitwise_xor.reduceat(bits, np.cumsum(sizes) - sizes)


def _runs(buckets: int, edits: int, least: int, exact: int):
    """Texts to sorted runs: distinct lines (kind 0) and their keys (kind 1)."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from xxhash import xxh3_128_digest

        plans: dict = {}
        seen: dict[bytes, tuple[int, int, int]] = {}
        keys: list[list[int]] = [[], []]
        refs: list[list[int]] = [[], []]
        fresh: list[bytes] = []
        marks: list[np.ndarray] = []
        held = 0
        edges = (np.arange(1, buckets, dtype=np.float64) / buckets * 2.0**64).astype(np.uint64)

        def mark() -> None:
            nonlocal held
            if fresh:
                marks.append(sketches(fresh))
            fresh.clear()
            held = 0

        def parts(by: np.ndarray, kind: int, *cols: np.ndarray) -> Iterator[tuple]:
            order = np.argsort(by, kind="stable")
            cut = np.concatenate([[0], np.searchsorted(by[order], edges), [len(by)]])
            for k in np.flatnonzero(np.diff(cut)).tolist():
                piece = [c[order[cut[k] : cut[k + 1]]].tobytes() for c in (by, *cols)]
                yield (k, kind, *piece, *[b""] * (5 - len(piece)))

        def flush() -> pa.RecordBatch:
            ids = np.frombuffer(b"".join(seen), ">u8").reshape(-1, 2).astype(np.uint64)
            at = np.array(list(seen.values()), np.int64).reshape(-1, 3)
            mark()
            # a line goes by 32 bits of its hash and its sketch; the other 64 keep it apart
            ids[:, 0] = (ids[:, 0] & np.uint64(0xFFFFFFFF00000000)) | np.concatenate(marks)
            rows = list(parts(ids[:, 0], 0, ids[:, 1], at[:, 0], at[:, 1], at[:, 2]))
            k = np.array(keys[0] + keys[1], np.uint64)
            side = np.concatenate([np.zeros(len(keys[0]), np.uint8), np.ones(len(keys[1]), np.uint8)])
            rows += parts(k, 1, ids[np.array(refs[0] + refs[1], np.int64), 0], side)
            marks.clear()
            seen.clear()
            for x in (*keys, *refs):
                x.clear()
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), _RUN_TYPES, strict=True)], _RUN_NAMES)

        for b in batches:
            for doc, of, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).cast(pa.binary()).to_pylist(), strict=True):
                for no, line in enumerate(t.split(b"\n")):
                    if len(line) < exact:
                        continue
                    name = xxh3_128_digest(line)
                    was = seen.get(name)
                    if was is None:
                        seen[name] = (doc, of, no)
                        own, look = line_keys(line, plans, edits) if len(line) >= least else ((), ())
                        ref = len(seen) - 1
                        fresh.append(line)
                        held += len(line)
                        if held > 1 << 20:
                            mark()
                        keys[0] += own
                        keys[1] += look
                        refs[0] += [ref] * len(own)
                        refs[1] += [ref] * len(look)
                    elif (doc, of, no) < was:
                        seen[name] = (doc, of, no)
                if len(keys[1]) > 400_000 or len(seen) > 100_000:
                    yield flush()
        if seen:
            yield flush()

    return run


def _columns(batches: Iterable[pa.RecordBatch], kinds: tuple) -> list[np.ndarray]:
    got: list[list[np.ndarray]] = [[] for _ in kinds]
    for b in batches:
        for k, kind in enumerate(kinds):
            got[k] += [np.frombuffer(x.as_buffer(), kind) for x in b.column(k)]
    return [np.concatenate(x) if x else np.empty(0, k) for x, k in zip(got, kinds, strict=True)]


_LINE = ["hi", "lo", "doc", "of", "no"]


def _first_lines(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    hi, lo, doc, of, no = _columns(batches, (np.uint64, np.uint64, np.int64, np.int64, np.int64))
    order = np.lexsort((no, of, doc, lo, hi))
    hi, lo, doc, of, no = (x[order] for x in (hi, lo, doc, of, no))
    first = np.ones(len(hi), bool)
    first[1:] = (hi[1:] != hi[:-1]) | (lo[1:] != lo[:-1])
    for at in range(0, len(hi), 500_000):
        f = np.flatnonzero(first[at : at + 500_000]) + at
        yield pa.RecordBatch.from_arrays([pa.array(x[f].view(np.int64)) for x in (hi, lo, doc, of, no)], _LINE)


def _meet(batches: Iterable[pa.RecordBatch], edits: int) -> Iterator[pa.RecordBatch]:
    """Lines whose index and probe keys agree, each pair once for a range of keys."""
    key, ref, side = _columns(batches, (np.uint64, np.uint64, np.uint8))
    own, look = side == 0, side == 1
    order = np.argsort(key[own], kind="stable")
    k, r = key[own][order], ref[own][order]
    pk, pr = key[look], ref[look]
    lo, hi = np.searchsorted(k, pk, "left"), np.searchsorted(k, pk, "right")
    hit = np.flatnonzero(hi > lo)
    lo, n, pr = lo[hit], (hi - lo)[hit], pr[hit]
    ends = np.cumsum(n)
    at = 0
    while at < len(n):  # in blocks of about two million pairs
        base = ends[at - 1] if at else 0
        to = max(at + 1, int(np.searchsorted(ends, base + 2_000_000, "right")))
        a = np.repeat(pr[at:to], n[at:to])
        inner = np.arange(len(a)) - np.repeat(ends[at:to] - n[at:to] - base, n[at:to])
        b = r[np.repeat(lo[at:to], n[at:to]) + inner]
        # far sketches cannot meet: only pairs that may lie within the edits leave the task
        differ = (a != b) & (np.bitwise_count((a ^ b) & np.uint64(0xFFFFFFFF)) <= 2 * edits)
        pair = np.unique(np.stack([np.minimum(a, b)[differ], np.maximum(a, b)[differ]], 1), axis=0)
        yield pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(pair[:, i]).view(np.int64)) for i in (0, 1)], ["a", "b"])
        at = to


def line_classes(docs: DataFrame, id_col: str, text: str, edits: int = EDITS, least: int = LEAST, exact: int = LEAST) -> DataFrame:
    """``doc, of, nos``: for each document (id and hash of its text) the places of the lines that stay, as a sorted array."""
    from xxhash import xxh3_128_digest

    spark = docs.sparkSession
    buckets = n_buckets(spark)
    rows = docs.select(_doc(id_col).alias("doc"), F.xxhash64(F.col(f"`{text}`").cast("string")).alias("of"), F.col(f"`{text}`").cast("string").alias("text")).where("text is not null")
    runs = spool(rows.mapInArrow(_runs(buckets, edits, least, exact), RUNS), "line-runs")
    lines = spool(runs.where("kind = 0").repartition(buckets, "bucket").select("a", "b", "c", "d", "e").mapInArrow(_first_lines, ", ".join(f"{c} long" for c in _LINE)), "lines")
    pairs = spool(runs.where("kind = 1").repartition(buckets, "bucket").select("a", "b", "c").mapInArrow(lambda x: _meet(x, edits), "a long, b long").distinct(), "line-pairs")
    wanted = pairs.select(F.col("a").alias("hi")).union(pairs.select("b")).distinct()
    places = lines.join(wanted, "hi", "left_semi").groupBy("doc", "of").agg(F.collect_list(F.struct("no", "hi", "lo")).alias("want"))

    def fetch(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out: list[tuple] = []
            for t, want in zip(b.column(0).cast(pa.binary()).to_pylist(), b.column(1).to_pylist(), strict=True):
                split = t.split(b"\n")
                for w in want:
                    line = split[w["no"]] if w["no"] < len(split) else b""
                    if int.from_bytes(xxh3_128_digest(line)[8:], "big", signed=True) == w["lo"]:
                        out.append((w["hi"], w["lo"], line))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True), (pa.int64(), pa.int64(), pa.binary()), strict=True)], ["hi", "lo", "line"])

    texts = spool(rows.join(places, ["doc", "of"]).select("text", "want").mapInArrow(fetch, "hi long, lo long, line binary").dropDuplicates(["hi", "lo"]), "line-texts")

    def verify(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ok = [within(x, y, edits) for x, y in zip(b.column(4).to_pylist(), b.column(5).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays(b.columns[:4], ["a", "al", "b", "bl"]).filter(pa.array(ok, pa.bool_()))

    left = texts.select(F.col("hi").alias("a"), F.col("lo").alias("al"), F.col("line").alias("x"))
    right = texts.select(F.col("hi").alias("b"), F.col("lo").alias("bl"), F.col("line").alias("y"))
    links = pairs.join(left, "a").join(right, "b").select("a", "al", "b", "bl", "x", "y").mapInArrow(verify, "a long, al long, b long, bl long")
    name = lambda hi, lo: F.struct(F.col(hi).alias("hi"), F.col(lo).alias("lo"))
    label = components(spool(links.select(name("a", "al").alias("a"), name("b", "bl").alias("b")), "line-links"))
    label = label.select("node.hi", "node.lo", "label")
    named = lines.join(label, ["hi", "lo"], "left")
    first = named.groupBy(F.coalesce("label", name("hi", "lo")).alias("k")).agg(F.min(F.struct("doc", "of", "no")).alias("f"))
    return first.groupBy(F.col("f.doc").alias("doc"), F.col("f.of").alias("of")).agg(F.sort_array(F.collect_list(F.col("f.no"))).alias("nos"))


def _doc(id_col: str) -> Column:
    return F.coalesce(F.col(f"`{id_col}`").cast("long"), F.lit(NO_ID))


def dedup_lines(docs: DataFrame, id_col: str = "doc_id", text: str = "text", edits: int = EDITS, least: int = LEAST, report: bool = True, exact: int | None = None) -> DataFrame:
    """``docs`` with removed lines cut from ``text``; with ``report`` adds ``n_lines, n_removed``
    (with underscores in front where ``docs`` has such columns).  Equal lines of ``exact``
    bytes (``least`` if not given) and more are removed; empty lines never are."""
    exact = max(1, min(least, least if exact is None else exact))
    doc, of, stay, n, gone = unused(docs, "line_doc", "line_of", "line_nos", "n_lines", "n_removed")
    kept = line_classes(docs, id_col, text, edits, least, exact).select(F.col("doc").alias(doc), F.col("of").alias(of), F.col("nos").alias(stay))
    both = docs.withColumn(text, F.col(f"`{text}`").cast("string"))
    both = both.join(kept, (_doc(id_col) == F.col(doc)) & (F.xxhash64(F.col(f"`{text}`")) == F.col(of)), "left").drop(doc, of)
    names = both.columns
    at, last = names.index(text), names.index(stay)
    out_names = [c for c in names if c != stay] + [n, gone] * report

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts, total, cut = [], [], []
            for t, nos in zip(b.column(at).cast(pa.binary()).to_pylist(), b.column(last).to_pylist(), strict=True):
                if t is None:
                    texts.append(None)
                    total.append(0)
                    cut.append(0)
                    continue
                own, split = set(nos or ()), t.split(b"\n")
                left = [x for k, x in enumerate(split) if len(x) < exact or k in own]
                texts.append(b"\n".join(left))
                total.append(len(split))
                cut.append(len(split) - len(left))
            cols = [pa.array(texts, pa.binary()).cast(pa.string()) if k == at else c for k, c in enumerate(b.columns) if k != last]
            yield pa.RecordBatch.from_arrays([*cols, *[pa.array(total, pa.int64()), pa.array(cut, pa.int64())] * report], out_names)

    fields = [f for f in both.schema.fields if f.name != stay]
    return both.mapInArrow(run, T.StructType([*fields, *[T.StructField(c, T.LongType()) for c in (n, gone)] * report]))
