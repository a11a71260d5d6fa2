"""Repeated passages: common-prefix-aware merge sort of sampled suffixes.

A byte goes if a string of ``span`` bytes over it also starts in a document with a
smaller id.  Every such string chooses one *anchor*: the start of the ``gram``
bytes in it with the least hash.  Equal strings choose the same anchor, so two
documents share a string only if they share an anchor's bytes; suffixes need to be
sorted at anchors only, about one in eighteen positions.

1. Texts become chunk rows.  Each chunk sends its anchors' hashes as sorted runs
   by range; the task of a range answers which of them occur in different texts.
2. For those anchors each chunk sends suffixes as sorted, front-coded runs by
   range of the anchor hash, equal ones of a chunk once, with the bytes before the
   anchor that its strings reach.  The task of a range merges the runs with a loser
   tree that keeps, at every node, the prefix known to be shared with the last
   winner: lengths decide most matches, and bytes already compared are not read
   again.  Suffixes of one anchor come out together, and a table of their strings
   in order of document id tells which of them came earlier.
3. The spans found go back to their chunks, where they are cut out.

Texts that equal one of a smaller id are settled by a text hash and do not send
suffixes.  All hashes are filters except that one (128 bits); decisions rest on bytes.

Cases: null text is empty; a null id neither loses nor removes bytes; rows that
share an id do not remove each other's bytes; texts shorter than ``span`` stay;
matches never cross documents; an empty table gives no rows; further columns are
not read.
"""

from __future__ import annotations

import hashlib
from array import array
from collections.abc import Iterable, Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import CHUNK_SCHEMA, open_chunk, range_count, spool, to_chunks

SPAN, GRAM, FAN_IN = 50, 16, 256
#: Texts of a chunk, in bytes, and chunks for each range: what a task holds at once.
TEXT_BYTES, RANGE_CHUNKS = 2 << 20, 6
#: Rows of a run whose columns are opened at once; spans that leave a range together.
OPEN_ROWS, SPAN_ROWS = 2048, 100_000
_CHUNK = [f.split()[0] for f in CHUNK_SCHEMA.split(", ")]
_ODD = np.uint64(0x9E3779B97F4A7C15)
_ODD_INVERSE = np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))
_POWERS: list[np.ndarray] = []


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if not _POWERS or len(_POWERS[0]) < n:
        size = max(n, BLOCK + (1 << 17))
        _POWERS[:] = [np.cumprod(np.concatenate([[np.uint64(1)], np.full(size - 1, b, np.uint64)]), dtype=np.uint64) for b in (_ODD, _ODD_INVERSE)]
    return _POWERS[0][:n], _POWERS[1][:n]


def gram_hashes(x: np.ndarray, gram: int = GRAM) -> np.ndarray:
    """A mixed 64-bit hash of the ``gram`` bytes from each place."""
    n = len(x)
    up, down = _powers(n)
    sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum((x.astype(np.uint64) + np.uint64(1)) * down, dtype=np.uint64)])
    h = (sums[gram:] - sums[:-gram]) * up[: n - gram + 1]
    h ^= h >> np.uint64(31)
    h *= np.uint64(0xD6E8FEB86659FD93)
    h ^= h >> np.uint64(32)
    h *= np.uint64(0xD6E8FEB86659FD93)
    h ^= h >> np.uint64(32)
    return h


#: Bytes whose hashes are held at once.
BLOCK = 1 << 19


def anchors(x: np.ndarray, sizes: np.ndarray, span: int = SPAN, gram: int = GRAM):
    """Anchors of texts laid end to end: hash, place, first and last string start."""
    out, at, first, ends = [], 0, 0, np.cumsum(sizes)
    while first < len(sizes):  # some whole texts at a time
        last = max(first + 1, int(np.searchsorted(ends, at + BLOCK, "right")))
        got = _anchors(x[at : ends[last - 1]], sizes[first:last], span, gram)
        out.append((got[0], *[c + at for c in got[1:]]))
        first, at = last, int(ends[last - 1])
    if not out:
        return np.empty(0, np.uint64), *[np.empty(0, np.int64)] * 3
    return tuple(np.concatenate(c) for c in zip(*out, strict=True))


def _anchors(x: np.ndarray, sizes: np.ndarray, span: int, gram: int):
    none = np.empty(0, np.int64)
    if len(x) < span:
        return np.empty(0, np.uint64), none, none, none
    h = gram_hashes(x, gram)
    width, have = span - gram + 1, 1
    value, place = h, np.arange(len(h), dtype=np.int32 if len(h) < 1 << 31 else np.int64)
    while have < width:  # leftmost minimum of doubling windows
        by = min(have, width - have)
        n = len(value) - by
        right = value[by:] < value[:n]
        value, place = np.where(right, value[by:], value[:n]), np.where(right, place[by:], place[:n])
        have += by
    ends = np.cumsum(sizes)
    text = np.repeat(np.arange(len(sizes)), sizes)[: len(place)]
    ok = np.arange(len(place)) + span <= ends[text]
    s, p, t = np.flatnonzero(ok), place[ok].astype(np.int64), text[ok]
    if not len(s):
        return np.empty(0, np.uint64), none, none, none
    new = np.flatnonzero(np.concatenate([[True], (p[1:] != p[:-1]) | (t[1:] != t[:-1])]))
    last = np.concatenate([new[1:] - 1, [len(s) - 1]])
    return h[p[new]], p[new], s[new], s[last]


class Anchored:
    """A chunk's texts with their anchors; every pass rebuilds the same one."""

    def __init__(self, row: dict, span: int, gram: int):
        self.ids, self.texts = open_chunk(row["n"], row["ids"], row["known"], row["lens"], row["payload"])
        self.span = span
        self.part = [k for k, (i, t) in enumerate(zip(self.ids, self.texts, strict=True)) if i is not None and len(t) >= span]
        self.sizes = np.array([len(self.texts[k]) for k in self.part], np.int64)
        self.raw = b"".join([self.texts[k] for k in self.part])
        self.doc = np.array([self.ids[k] for k in self.part], np.int64)
        self.ends = np.cumsum(self.sizes)

    def find(self, gram: int) -> None:
        from xxhash import xxh3_128_digest

        self.h, self.p, self.lo, self.hi = anchors(np.frombuffer(self.raw, np.uint8), self.sizes, self.span, gram)
        self.of = np.searchsorted(self.ends, self.p, "right")
        self.order = np.argsort(self.h, kind="stable")
        sorted_h = self.h[self.order]
        self.first = np.flatnonzero(np.concatenate([[True], sorted_h[1:] != sorted_h[:-1]])) if len(sorted_h) else np.empty(0, np.int64)
        self.names = sorted_h[self.first]
        self.text_hash = np.frombuffer(b"".join([xxh3_128_digest(self.texts[k]) for k in self.part]), ">u8").reshape(-1, 2).astype(np.uint64)
        self.text_order = np.lexsort((self.text_hash[:, 1], self.text_hash[:, 0]))


def _cut(names: np.ndarray, edges: np.ndarray) -> np.ndarray:
    return np.concatenate([[0], np.searchsorted(names, edges), [len(names)]])


def _edges(buckets: int) -> np.ndarray:
    return (np.arange(1, buckets, dtype=np.float64) / buckets * 2.0**64).astype(np.uint64)


HASH_RUN = "bucket int, kind int, chunk long, a binary, b binary, c binary, d binary, e binary"
_HASH_TYPES = [pa.int32(), pa.int32(), pa.int64()] + [pa.binary()] * 5


def _batch(rows: list[tuple], types: list, kind: str) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], [f.split()[0] for f in kind.split(", ")])


def _hash_runs(buckets: int, span: int, gram: int):
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        edges = _edges(buckets)
        for b in batches:
            for row in b.to_pylist():
                c = Anchored(row, span, gram)
                if not len(c.doc):
                    continue
                c.find(gram)
                rows = []
                if len(c.names):
                    text = c.text_hash[c.of[c.order], 0]
                    least, most = np.minimum.reduceat(text, c.first), np.maximum.reduceat(text, c.first)
                    idx = c.of[c.order][c.first].astype(np.uint16)
                    cut, table = _cut(c.names, edges), np.ascontiguousarray(c.text_hash[:, 0]).tobytes()
                    for k in np.flatnonzero(np.diff(cut)).tolist():
                        s = slice(cut[k], cut[k + 1])
                        rows.append((k, 0, row["chunk"], (c.names[s] >> np.uint64(32)).astype(np.uint32).tobytes(), (c.names[s] >> np.uint64(16)).astype(np.uint16).tobytes(), idx[s].tobytes(), np.packbits(least[s] != most[s]).tobytes(), table))
                hi, lo = c.text_hash[c.text_order, 0], c.text_hash[c.text_order, 1]
                cut = _cut(hi, edges)
                for k in np.flatnonzero(np.diff(cut)).tolist():
                    s = slice(cut[k], cut[k + 1])
                    rows.append((k, 1, row["chunk"], hi[s].tobytes(), lo[s].tobytes(), c.doc[c.text_order][s].tobytes(), b"", b""))
                yield _batch(rows, _HASH_TYPES, HASH_RUN)

    return run


ANSWER = "chunk long, kind int, bucket int, bits binary"
_ANSWER_TYPES = [pa.int64(), pa.int32(), pa.int32(), pa.binary()]


def _answers(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """For each run: which anchors lie in different texts, which texts come later than an equal one."""
    held: dict[tuple[int, int], list[tuple]] = {}
    for b in batches:
        for r in b.to_pylist():
            held.setdefault((r["kind"], r["bucket"]), []).append((r["chunk"], r["a"], r["b"], r["c"], r["d"], r["e"]))
    for kind, bucket in list(held):
        runs, rows = held.pop((kind, bucket)), []
        if kind == 0:
            key = np.concatenate([(np.frombuffer(r[1], np.uint32).astype(np.uint64) << np.uint64(16)) | np.frombuffer(r[2], np.uint16) for r in runs])
            text = np.concatenate([np.frombuffer(r[5], np.uint64)[np.frombuffer(r[3], np.uint16)] for r in runs])
            multi = np.concatenate([np.unpackbits(np.frombuffer(r[4], np.uint8), count=len(r[1]) // 4) for r in runs])
            sizes = [len(r[1]) // 4 for r in runs]
            order = np.argsort(key, kind="stable")
            sorted_key = key[order]
            first = np.concatenate([[True], sorted_key[1:] != sorted_key[:-1]])
            at = np.flatnonzero(first)
            hit = (np.minimum.reduceat(text[order], at) != np.maximum.reduceat(text[order], at)) | (np.maximum.reduceat(multi[order], at) > 0)
        else:
            hi, lo, doc = (np.concatenate([np.frombuffer(r[k], t) for r in runs]) for k, t in ((1, np.uint64), (2, np.uint64), (3, np.int64)))
            sizes = [len(r[1]) // 8 for r in runs]
            order = np.lexsort((doc, lo, hi))
            first = np.concatenate([[True], (hi[order][1:] != hi[order][:-1]) | (lo[order][1:] != lo[order][:-1])])
            least = doc[order][np.flatnonzero(first)]
        group = np.cumsum(first) - 1
        flag = np.empty(len(order), bool)
        flag[order] = hit[group] if kind == 0 else doc[order] > least[group]
        end = 0
        for r, n in zip(runs, sizes, strict=True):
            rows.append((r[0], kind, bucket, np.packbits(flag[end : end + n]).tobytes()))
            end += n
        yield _batch(rows, _ANSWER_TYPES, ANSWER)


def _bits(parts: list[dict], kind: int, cut: np.ndarray) -> np.ndarray:
    got = {p["bucket"]: p["bits"] for p in parts if p["kind"] == kind}
    full = [np.unpackbits(np.frombuffer(got[k], np.uint8), count=int(cut[k + 1] - cut[k])) for k in np.flatnonzero(np.diff(cut)).tolist()]
    return np.concatenate(full).astype(bool) if full else np.empty(0, bool)


SPANS = "bucket int, kind int, chunk long, payload binary"
_SPAN_TYPES = [pa.int32(), pa.int32(), pa.int64(), pa.binary()]


def front_code(rows: list[tuple[bytes, bytes, int, int]], span: int) -> bytes:
    """Sorted ``(suffix, left, doc, place)`` as one compressed run."""
    import zstandard

    keep, tails, last, last_len = [], [], 0, 0
    for s, *_ in rows:
        v = int.from_bytes(s.ljust(span, b"\0"), "big")
        same = min((8 * span - (v ^ last).bit_length()) >> 3, len(s), last_len)
        keep.append(same)
        tails.append(s[same:])
        last, last_len = v, len(s)
    n = len(rows)
    parts = [np.array(keep, np.uint8), np.array([len(r[0]) for r in rows], np.uint8), np.array([len(r[1]) for r in rows], np.uint8), np.array([r[2] for r in rows], np.int64), np.array([r[3] for r in rows], np.uint32)]
    raw = n.to_bytes(4, "little") + b"".join(p.tobytes() for p in parts) + b"".join(tails) + b"".join(r[1] for r in rows)
    return zstandard.ZstdCompressor(level=1).compress(raw)


def read_run(raw: bytes, chunk: int, span: int) -> Iterator[tuple]:
    """``(suffix as a number, prefix shared with the one before, suffix, left, doc, chunk, place)``."""
    import zstandard

    raw = zstandard.ZstdDecompressor().decompress(raw)
    n, at, cols = int.from_bytes(raw[:4], "little"), 4, []
    for t in (np.uint8, np.uint8, np.uint8, np.int64, np.uint32):
        cols.append(np.frombuffer(raw, t, n, at))
        at += n * np.dtype(t).itemsize
    left_at = at + int(cols[1].sum(dtype=np.int64)) - int(cols[0].sum(dtype=np.int64))
    last = b""
    for lo in range(0, n, OPEN_ROWS):
        for same, size, left, doc, place in zip(*(c[lo : lo + OPEN_ROWS].tolist() for c in cols), strict=True):
            tail = size - same
            last = last[:same] + raw[at : at + tail]
            at += tail
            yield int.from_bytes(last.ljust(span, b"\0"), "big"), same, last, raw[left_at : left_at + left], doc, chunk, place
            left_at += left


def merge_runs(runs: list[Iterator[tuple]], span: int = SPAN) -> Iterator[tuple]:
    """Loser tree over sorted runs; yields rows with the prefix shared with the row before."""
    if len(runs) > FAN_IN:
        runs = [merge_runs(runs[k : k + FAN_IN], span) for k in range(0, len(runs), FAN_IN)]
    rows, known = [], []  # the head of each run; prefix it shares with the last winner
    live = []
    for r in runs:
        head = next(r, None)
        if head is not None:
            live.append(r)
            rows.append(head)
            known.append(0)
    k, bits = len(live), 8 * span
    if not k:
        return
    end = (1 << bits) + 1

    def play(i: int, j: int) -> tuple[int, int]:
        """Winner and loser; the loser remembers what it shares with the winner."""
        if known[i] != known[j]:
            return (i, j) if known[i] > known[j] else (j, i)
        a, b = rows[i][0], rows[j][0]
        if a <= b:
            known[j] = max(0, (bits - (a ^ b).bit_length()) >> 3)
            return i, j
        known[i] = max(0, (bits - (a ^ b).bit_length()) >> 3)
        return j, i

    lost = [0] * k  # node n has children 2n and 2n+1; leaves are k..2k-1
    won = [0] * k + list(range(k))
    for n in range(k - 1, 0, -1):
        won[n], lost[n] = play(won[2 * n], won[2 * n + 1])
    top = won[1]
    while True:
        row = rows[top]
        if row[0] == end:
            return
        yield (row[0], known[top], *row[2:])
        nxt = next(live[top], None)
        if nxt is None:
            rows[top], known[top] = (end, 0), -1
        else:
            rows[top], known[top] = nxt, nxt[1]
        n = (top + k) >> 1
        while n:
            other = lost[n]
            a, b = known[top], known[other]
            if a == b:
                if a == -1:
                    pass
                else:
                    x, y = rows[top][0], rows[other][0]
                    same = (bits - (x ^ y).bit_length()) >> 3
                    if x <= y:
                        known[other] = same
                    else:
                        known[top], lost[n], top = same, top, other
            elif a < b:
                lost[n], top = top, other
            n >>= 1


def _earlier(group: list[tuple], span: int) -> Iterator[tuple[int, int, int]]:
    """``(chunk, first, last)`` string starts of a group that occur in an earlier document."""
    least: dict[tuple[bytes, bytes], int] = {}
    for _, _, s, left, doc, _, _ in group:
        key = (left, s)
        if doc < least.get(key, doc + 1):
            least[key] = doc
    part: dict[tuple[bytes, bytes], list[int]] = {}
    if len(least) > 1:
        seen: dict[bytes, int] = {}
        for key, doc in sorted(least.items(), key=lambda x: x[1]):
            left, s = key
            gone = []
            for o in range(max(0, span - len(s)), len(left) + 1):
                text = left[len(left) - o :] + s[: span - o]
                if seen.setdefault(text, doc) < doc:
                    gone.append(o)
            part[key] = gone
    for _, _, s, left, doc, chunk, place in group:
        key = (left, s)
        if doc > least[key]:
            yield chunk, place - len(left), place - max(0, span - len(s))
        elif gone := part.get(key):
            first = last = gone[0]
            for o in gone[1:]:
                if o != last + 1:
                    yield chunk, place - last, place - first
                    first = o
                last = o
            yield chunk, place - last, place - first


def _suffix_runs(buckets: int, span: int, gram: int):
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        edges = _edges(buckets)
        for b in batches:
            for row in b.to_pylist():
                c = Anchored(row, span, gram)
                if not len(c.doc):
                    continue
                c.find(gram)
                later = np.zeros(len(c.doc), bool)
                later[c.text_order] = _bits(row["answers"], 1, _cut(c.text_hash[c.text_order, 0], edges))
                shared = np.zeros(len(c.h), bool)
                if len(c.names):
                    flags = _bits(row["answers"], 0, _cut(c.names, edges))
                    shared[c.order] = np.repeat(flags, np.diff(np.append(c.first, len(c.h))))
                take = c.order[(shared & ~later[c.of])[c.order]]  # in order of anchor hash
                starts = c.ends - c.sizes
                spans = [(int(starts[k]), int(c.ends[k] - span)) for k in np.flatnonzero(later).tolist()]
                first: dict[tuple[bytes, bytes], list] = {}
                docs = c.doc[c.of[take]].tolist()
                for h, p, lo, hi, doc in zip(c.h[take].tolist(), c.p[take].tolist(), c.lo[take].tolist(), c.hi[take].tolist(), docs, strict=True):
                    key = (c.raw[lo:p], c.raw[p : hi + span])
                    was = first.get(key)
                    if was is None:
                        first[key] = [h, doc, p, lo, hi]
                    elif doc > was[1]:
                        spans.append((lo, hi))
                    elif doc < was[1]:
                        spans.append((was[3], was[4]))
                        first[key] = [h, doc, p, lo, hi]
                    else:  # the same document again: both answers are needed
                        first[(*key, p)] = [h, doc, p, lo, hi]
                sends = sorted(((v[0], key[1], key[0], v[1], v[2]) for key, v in first.items()), key=lambda x: x[0])
                cut = _cut(np.array([s[0] for s in sends], np.uint64), edges)
                rows = [(k, 0, row["chunk"], front_code(sorted(s[1:] for s in sends[cut[k] : cut[k + 1]]), span)) for k in np.flatnonzero(np.diff(cut)).tolist()]
                if spans:
                    rows.append((row["chunk"] % buckets, 1, row["chunk"], np.array(spans, np.uint32).tobytes()))
                if rows:
                    yield _batch(rows, _SPAN_TYPES, SPANS)

    return run


def _merged(span: int, gram: int):
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        runs: dict[int, list[Iterator]] = {}
        for b in batches:
            for bucket, kind, chunk, payload in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if kind == 1:
                    yield _batch([(bucket, 1, chunk, payload)], _SPAN_TYPES, SPANS)
                else:
                    runs.setdefault(bucket, []).append(read_run(payload, chunk, span))
        for bucket in list(runs):
            found: dict[int, array] = {}
            group: list[tuple] = []
            held = 0
            for row in chain(merge_runs(runs.pop(bucket), span), [(0, 0)]):  # the last one ends the last group
                if row[1] < gram:
                    if len(group) > 1:
                        for chunk, lo, hi in _earlier(group, span):
                            found.setdefault(chunk, array("I")).extend((lo, hi))
                            held += 1
                    group = []
                    if held > SPAN_ROWS:
                        yield _batch([(bucket, 1, chunk, s.tobytes()) for chunk, s in found.items()], _SPAN_TYPES, SPANS)
                        found, held = {}, 0
                group.append(row)
            if found:
                yield _batch([(bucket, 1, chunk, s.tobytes()) for chunk, s in found.items()], _SPAN_TYPES, SPANS)

    return run


def _apply(span: int, gram: int, keep_text: bool):
    kind = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + ", kept binary" * keep_text
    types = [pa.int64()] * 4 + [pa.string()] + [pa.binary()] * keep_text

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for row in b.to_pylist():
                c = Anchored(row, span, gram)
                gone = np.zeros(len(c.raw) + 1, np.int32)
                for s in row["spans"] or ():
                    at = np.frombuffer(s, np.uint32).astype(np.int64).reshape(-1, 2)
                    np.add.at(gone, at[:, 0], 1)
                    np.add.at(gone, at[:, 1] + span, -1)
                off = np.cumsum(gone[:-1]) > 0
                x = np.frombuffer(c.raw, np.uint8)
                place, rows = dict(zip(c.part, range(len(c.part)), strict=True)), []
                for k, (i, t) in enumerate(zip(c.ids, c.texts, strict=True)):
                    removed = spans = 0
                    if (j := place.get(k)) is not None:
                        mine = off[c.ends[j] - c.sizes[j] : c.ends[j]]
                        removed = int(mine.sum())
                        if removed:
                            spans = int(mine[0]) + int((mine[1:] & ~mine[:-1]).sum())
                            t = x[c.ends[j] - c.sizes[j] : c.ends[j]][~mine].tobytes()
                    rows.append((i, len(c.texts[k]), removed, spans, hashlib.sha256(t).hexdigest(), *[t] * keep_text))
                yield _batch(rows, types, kind)

    return run, kind


def cut_repeats(docs: DataFrame, id_col: str = "doc_id", text: str = "text", span: int = SPAN, gram: int = GRAM, keep_text: bool = True) -> DataFrame:
    """``doc_id, n_bytes, n_removed, n_spans, kept_sha256`` and ``kept`` bytes."""
    chunks = to_chunks(docs, id_col, text, "suffix-chunks", size=TEXT_BYTES)
    buckets = range_count(chunks, RANGE_CHUNKS)
    told = spool(chunks.mapInArrow(_hash_runs(buckets, span, gram), HASH_RUN).repartition(buckets, "bucket").mapInArrow(_answers, ANSWER), "suffix-flags")
    told = told.groupBy("chunk").agg(F.collect_list(F.struct("kind", "bucket", "bits")).alias("answers"))
    sent = chunks.join(told, "chunk").select(*_CHUNK, "answers").mapInArrow(_suffix_runs(buckets, span, gram), SPANS)
    found = spool(sent.repartition(buckets, "bucket").mapInArrow(_merged(span, gram), SPANS), "suffix-spans")
    spans = found.groupBy("chunk").agg(F.collect_list("payload").alias("spans"))
    run, kind = _apply(span, gram, keep_text)
    return chunks.join(spans, "chunk", "left").select(*_CHUNK, "spans").mapInArrow(run, kind)
