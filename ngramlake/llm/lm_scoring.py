"""Scores of every text under a count model and a self-attention model.

*Counts.*  A first pass makes chunk rows: the subword ids of the texts, and their words
as places in the chunk's sorted list of distinct word hashes.  A chunk's words travel as
sorted runs of hashes with their training counts, one run for each range; the task of a
range adds the counts of all chunks and answers each run with the totals of its words.
So a word crosses the network once for each chunk, however often it occurs, and no task
holds more than a range.

*Model.*  An id's probability is that of its class under causal self-attention over the
window, times that of the id in its class after the id before it.  The second factor
comes from counts of neighbouring ids in all training texts (pairs of the ``TOP`` most
frequent ids, backing off to the id's share of its class by the number of kinds seen);
so do the classes, from the neighbours of every id, and the first weights, from the
classes of neighbours.  From there the training windows of all chunks are descended, each
in one step of about ``SHARE`` batches; the weights of all tasks are averaged by steps.
Weights (not counts, pairs or classes) thus depend on how rows meet in chunks.

Cases: null text is empty and consists of its end alone; without training rows all
counts are 0 and the model stays as it began; equal texts get equal scores (to the
single precision of sums in other batches); null ids are kept and train; long texts are
whole; an empty table gives no rows; further columns are not read.
"""

from __future__ import annotations

import ctypes
import math
import zlib
from collections import defaultdict
from collections.abc import Iterable, Iterator
from itertools import chain, count, islice

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import attention as att
from .common import WordEncoder, n_buckets, range_count, spool, to_chunks

MODULUS, HELD, SHARE, BATCH, RATE = 7, 2, 1, 256, 0.002
#: Ids whose pairs are counted: their table (``TOP`` squared) is held by every task.
TOP = 2048
END_TEXT = "<|endoftext|>"
#: Words a Python worker keeps here: with fewer, rare ones are cut into subwords again and again.
CACHE = 250_000
#: Texts of a chunk, in bytes, and chunks for each range of word hashes.
TEXT_BYTES, RANGE_CHUNKS = 2 << 20, 12


def held_out(doc) -> bool:
    return doc is not None and zlib.crc32(str(doc).encode()) % MODULUS == HELD


def _between(codes: np.ndarray, size: np.ndarray, end: int, before: int) -> np.ndarray:
    """The codes with ``end`` after each text, and ``before`` more ahead of it."""
    out = np.full(len(codes) + (before + 1) * len(size), end, np.int64)
    out[np.arange(len(codes)) + np.repeat(np.arange(len(size)) * (before + 1) + before, size)] = codes
    return out


class Met:
    """The words that a worker has met: of each its subword ids and its hash in lower case.

    A text is then one look-up a word and numbers from there on; a word is worked on when it
    is new.  Above ``CACHE`` words, those of the last chunk are kept.
    """

    _own: dict[int, Met] = {}

    @classmethod
    def by(cls, encoder: WordEncoder) -> Met:
        if id(encoder) not in cls._own:
            cls._own[id(encoder)] = cls(encoder)
        return cls._own[id(encoder)]

    @classmethod
    def forget(cls) -> None:
        """Gives the memory back when a task ends: workers live on, and not all of them pack again."""
        for met in cls._own.values():
            met.encoder.words.clear()
        cls._own.clear()
        if hasattr(c := ctypes.CDLL(None), "malloc_trim"):
            c.malloc_trim(0)

    def __init__(self, encoder: WordEncoder):
        self.encoder = encoder
        self.code: defaultdict = defaultdict(count().__next__)
        self.flat, self.many, self.hashes = np.empty(0, "<u4"), np.empty(0, np.int64), np.empty(0, np.uint64)

    def read(self, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """The words of all texts, as codes, and the words of each text."""
        from xxhash import xxh3_64_intdigest

        rows = [t.split() for t in texts]
        size = np.fromiter(map(len, rows), np.int64, len(rows))
        codes = np.fromiter(map(self.code.__getitem__, chain.from_iterable(rows)), np.int64, int(size.sum()))
        new = list(islice(self.code, len(self.many), None))
        got = self.encoder.encode_words(new)
        lower = b" ".join(new).lower().split()
        self.flat = np.concatenate([self.flat, np.frombuffer(b"".join(got), "<u4")])
        self.many = np.concatenate([self.many, np.fromiter(map(len, got), np.int64, len(got)) >> 2])
        self.hashes = np.concatenate([self.hashes, np.fromiter(map(xxh3_64_intdigest, lower), np.uint64, len(lower))])
        return (self._keep(codes) if len(self.code) > CACHE else codes), size

    def _keep(self, codes: np.ndarray) -> np.ndarray:
        """Forgets all words but these, and returns their new codes."""
        here = np.zeros(len(self.many), bool)
        here[codes] = True
        words, at = list(self.code), np.flatnonzero(here)
        self.flat, self.many, self.hashes = self.flat[np.repeat(here, self.many)], self.many[at], self.hashes[at]
        self.code = defaultdict(count(len(at)).__next__, zip(map(words.__getitem__, at.tolist()), range(len(at)), strict=True))
        if len(self.encoder.words) > CACHE:
            self.encoder.words.clear()
        return (np.cumsum(here) - 1)[codes]

    def subwords(self, codes: np.ndarray, size: np.ndarray, end: int) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts, each between two end ids, and the texts' offsets."""
        flat, n = np.append(self.flat, np.uint32(end)), np.append(self.many, 1)
        codes = _between(codes, size, len(self.many), 1)
        first, many = (np.cumsum(n) - n)[codes], n[codes]
        upto = np.cumsum(many)
        total = int(upto[-1]) if len(upto) else 0
        ids = flat[np.arange(total) + np.repeat(first - upto + many, many)].astype(np.int64)
        return ids, np.concatenate([[0], upto[np.cumsum(size + 2) - 1]])

    def names(self, codes: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Places of all tokens (ends included) in the sorted hashes of the distinct ones, tokens
        of each text, and these hashes."""
        from xxhash import xxh3_64_intdigest

        here = np.zeros(len(self.hashes), bool)
        here[codes] = True
        at = np.flatnonzero(here)
        hashes, place = np.unique(np.append(self.hashes[at], np.uint64(xxh3_64_intdigest(b""))), return_inverse=True)
        rank = np.zeros(len(self.hashes), np.uint32)
        rank[at] = place[:-1]
        return _between(rank[codes], size, int(place[-1]), 0).astype(np.uint32), size + 1, hashes


def _edges(buckets: int) -> np.ndarray:
    return (np.arange(1, buckets, dtype=np.float64) / buckets * 2.0**64).astype(np.uint64)


def _subwords(encoder: WordEncoder, texts: list[bytes], end: int) -> tuple[np.ndarray, np.ndarray]:
    met = Met.by(encoder)
    return met.subwords(*met.read(texts), end)


def _pack(path: str):
    """Subword ids of a chunk's texts (offsets, ids) and its words (places, sizes, hashes), compressed."""

    def pack(texts: list[bytes]) -> tuple[bytes, bytes, bytes]:
        import zstandard

        encoder = WordEncoder.get(path)
        met = Met.by(encoder)
        read = met.read(texts)
        ids, starts = met.subwords(*read, encoder.tokenizer.token_to_id(END_TEXT))
        codes, size, hashes = met.names(*read)
        out = []
        for most, tail, *head in ((encoder.tokenizer.get_vocab_size(), ids, starts), (1 << 32, codes, size)):
            sizes = b"".join(len(x).to_bytes(8, "little") for x in head)
            raw = sizes + b"".join(x.astype(np.int64).tobytes() for x in head) + tail.astype(np.uint16 if most <= 1 << 16 else np.uint32).tobytes()
            out.append(zstandard.ZstdCompressor(level=1).compress(raw))
        return *out, squeeze(hashes)

    pack.done = Met.forget
    return pack


def squeeze(x: np.ndarray) -> bytes:
    """Rising 64-bit numbers: steps from one to the next, byte place by byte place, compressed."""
    import zstandard

    step = np.diff(x.astype(np.uint64), prepend=np.uint64(0))
    return zstandard.ZstdCompressor(level=1).compress(step.view(np.uint8).reshape(-1, 8).T.tobytes())


def unsqueeze(raw: bytes) -> np.ndarray:
    import zstandard

    planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(raw), np.uint8).reshape(8, -1)
    return np.cumsum(np.ascontiguousarray(planes.T).view(np.uint64).ravel(), dtype=np.uint64)


def _open(raw: bytes, heads: int, most: int) -> list[np.ndarray]:
    """The arrays of ``_pack``: the narrow one first."""
    import zstandard

    raw = zstandard.ZstdDecompressor().decompress(raw)
    sizes, at, out = np.frombuffer(raw, np.int64, heads).tolist(), 8 * heads, []
    for n in sizes:
        out.append(np.frombuffer(raw, np.int64, n, at))
        at += 8 * n
    return [np.frombuffer(raw, np.uint16 if most <= 1 << 16 else np.uint32, -1, at), *out]


def _open_words(raw: bytes) -> tuple[np.ndarray, np.ndarray]:
    codes, size = _open(raw, 1, 1 << 32)
    return codes, size


def _doc_ids(r: dict) -> list:
    return [i if k else None for i, k in zip(np.frombuffer(r["ids"], np.int64).tolist(), r["known"], strict=True)]


def _training_ids(r: dict, vocab: int) -> tuple[np.ndarray, np.ndarray]:
    """Ids and offsets of a chunk's training texts."""
    ids, starts = _open(r["extra"], 1, vocab)
    keep, size = np.array([not held_out(i) for i in _doc_ids(r)], bool), np.diff(starts)
    return ids[np.repeat(keep, size)].astype(np.int64), np.concatenate([[0], np.cumsum(size[keep])])


def _n_windows(starts: np.ndarray) -> np.ndarray:
    return -(-(np.diff(starts) - 1) // att.STRIDE)


def id_counts(chunks: DataFrame, vocab: int) -> tuple[np.ndarray, dict[int, int]]:
    """How often each id is a goal in all training texts (one row for each id of the vocabulary
    at most); windows of all chunks before each chunk."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, windows = np.zeros(vocab, np.int64), []
        for b in batches:
            for r in b.to_pylist():
                x, starts = _training_ids(r, vocab)
                n += np.bincount(x, minlength=vocab)
                n -= np.bincount(x[starts[:-1]], minlength=vocab)  # a text's opening end is no goal
                windows.append((r["chunk"], int(_n_windows(starts).sum())))
        at = np.flatnonzero(n)
        yield pa.RecordBatch.from_arrays(
            [pa.array([*at.tolist(), *[None] * len(windows)], pa.int64()), pa.array([*n[at].tolist(), *[w for _, w in windows]], pa.int64()), pa.array([*[None] * len(at), *[c for c, _ in windows]], pa.int64())],
            ["id", "n", "chunk"],
        )

    got = spool(chunks.select("chunk", "ids", "known", "extra").mapInArrow(run, "id long, n long, chunk long"), "lm-ids")
    out = np.zeros(vocab, np.int64)
    for r in got.where("id is not null").groupBy("id").agg(F.sum("n").alias("n")).collect():
        out[r["id"]] = r["n"]
    before, n = {}, 0
    for c, w in sorted(tuple(r) for r in got.where("chunk is not null").select("chunk", "n").collect()):
        before[c] = n
        n += w
    return out, before


#: Ids of one range of the table of neighbours; rows of one range of the table of pairs.
RANGE, PAIR_ROWS = 2048, 64
NEAR_RUN = "part int, cells binary"


def _near_runs(vocab: int, rank: np.ndarray):
    """Sums of a task's neighbours, one run for each range of ids, and of its pairs of top
    ids (ranges below zero): cells as steps from the one before, with their counts."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard

        any_row, width, pair_width = False, 2 * att.NEAR * RANGE, PAIR_ROWS * TOP
        seen, pairs = np.zeros(-(-vocab // RANGE) * width, np.uint32), np.zeros(TOP * TOP, np.uint32)
        small = rank.astype(np.int32)
        for b in batches:
            for r in b.to_pylist():
                x, starts = _training_ids(r, vocab)
                for lo in range(0, len(starts) - 1, 200):  # ids of some texts at a time
                    own = starts[lo : lo + 201]
                    part = x[own[0] : own[-1]]
                    np.add.at(seen, att.neighbour_cells(part, own - own[0]), np.uint32(1))
                    top = small[part]
                    both = (top[:-1] >= 0) & (top[1:] >= 0)
                    both[own[1:-1] - own[0] - 1] = False  # pairs stay within a text
                    np.add.at(pairs, top[:-1][both] * TOP + top[1:][both], np.uint32(1))
                    any_row = True
        for table, size, name in ((seen, width, lambda k: k), (pairs, pair_width, lambda k: -1 - k)):
            for k in range(len(table) // size if any_row else 0):
                part = table[k * size : (k + 1) * size]
                at = np.flatnonzero(part)
                if len(at):
                    raw = np.diff(at, prepend=0).astype(np.uint32).tobytes() + part[at].tobytes()
                    yield pa.RecordBatch.from_arrays([pa.array([name(k)], pa.int32()), pa.array([zstandard.ZstdCompressor(level=1).compress(raw)], pa.binary())], ["part", "cells"])

    return run


def _near_sums(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Short vectors of a range of ids, or the counts of a range of pairs."""
    import zstandard

    held: dict[int, np.ndarray] = {}
    for b in batches:
        for k, cells in zip(*(b.column(i).to_pylist() for i in range(2)), strict=True):
            if k not in held:
                held[k] = np.zeros(RANGE * 2 * att.NEAR if k >= 0 else PAIR_ROWS * TOP, np.float64)
            step, n = np.frombuffer(zstandard.ZstdDecompressor().decompress(cells), np.uint32).reshape(2, -1)
            held[k][np.cumsum(step, dtype=np.int64)] += n
    for k, seen in held.items():
        total, x = att.project(seen.reshape(RANGE, -1)) if k >= 0 else (np.empty(0), seen)
        yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), pa.array([total.tobytes()], pa.binary()), pa.array([x.astype(np.float32).tobytes()], pa.binary())], ["part", "total", "x"])


def classes(chunks: DataFrame, vocab: int, end: int, rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Class of each id by its neighbours in all training texts; counts of pairs of top ids."""
    runs = chunks.select("ids", "known", "extra").mapInArrow(_near_runs(vocab, rank), NEAR_RUN)
    parts = -(-vocab // RANGE)
    total, x, pairs = np.zeros(parts * RANGE), np.zeros((parts * RANGE, 24), np.float32), np.zeros((TOP, TOP), np.float32)
    rows = runs.repartition(n_buckets(chunks.sparkSession), "part").mapInArrow(_near_sums, "part int, total binary, x binary")
    for r in spool(rows, "lm-near").toLocalIterator():  # a bounded table: ids of the vocabulary, pairs of top ids
        got = np.frombuffer(bytes(r["x"]), np.float32)
        if r["part"] < 0:
            pairs[(-1 - r["part"]) * PAIR_ROWS : -r["part"] * PAIR_ROWS] = got.reshape(PAIR_ROWS, TOP)
        else:
            s = slice(r["part"] * RANGE, (r["part"] + 1) * RANGE)
            total[s], x[s] = np.frombuffer(bytes(r["total"])), got.reshape(RANGE, -1)
    return att.cluster(total[:vocab], x[:vocab], end), pairs


class InClass:
    """Log probability of an id in its class, after the id before it."""

    def __init__(self, of: np.ndarray, counts: np.ndarray, rank: np.ndarray, pairs: np.ndarray):
        members, in_class = np.bincount(of, minlength=att.CLASSES), np.bincount(of, counts, att.CLASSES)
        share = (counts + 1) / (in_class[of] + members[of])
        top = np.flatnonzero(rank >= 0)
        top = top[np.argsort(rank[top])]
        kind = np.zeros((len(top), att.CLASSES), np.float32)
        kind[np.arange(len(top)), of[top]] = 1
        pairs = pairs[: len(top), : len(top)]
        n, kinds = pairs @ kind, (pairs > 0).astype(np.float32) @ kind  # by id before and class
        known = n / np.maximum(n + kinds, 1)
        own = of[top]
        p = pairs / np.maximum(n, 1)[:, own] * known[:, own] + (1 - known[:, own]) * share[top]
        self.rank, self.of = rank, of
        self.pair = np.log(np.maximum(p, 1e-30)).astype(np.float32)
        self.rest = np.log(np.maximum(1 - known, 1e-30)).astype(np.float32)
        self.share = np.log(share).astype(np.float32)

    def __call__(self, before: np.ndarray, ids: np.ndarray) -> np.ndarray:
        a, b = self.rank[before], self.rank[ids]
        if not len(self.pair):
            return self.share[ids]
        out = self.pair[a, b]
        odd = np.flatnonzero((a < 0) | (b < 0))
        if len(odd):
            back = np.where(a[odd] < 0, np.float32(0), self.rest[a[odd], self.of[ids[odd]]])
            out[odd] = self.share[ids[odd]] + back
        return out


def first_weights(of: np.ndarray, rank: np.ndarray, pairs: np.ndarray) -> dict:
    """Weights that give the class after a class by the pairs of all training texts, as far as
    ``DIM`` numbers a class can; attention begins close to nothing."""
    w = att.fresh()
    top = np.flatnonzero(rank >= 0)
    own = of[top[np.argsort(rank[top])]]
    kind = np.zeros((len(own), att.CLASSES))
    kind[np.arange(len(own)), own] = 1
    n = kind.T @ pairs[: len(own), : len(own)].astype(np.float64) @ kind
    share = (n.sum(0) + 1) / (n.sum() + att.CLASSES)
    left, size, right = np.linalg.svd(np.log((n + share) / (n.sum(1, keepdims=True) + 1) / share))
    root = np.sqrt(size[: att.DIM])
    w["by_class"], w["u"], w["b"] = ((left[:, : att.DIM] * root).astype(np.float32), (root[:, None] * right[: att.DIM]).astype(np.float32), np.log(share).astype(np.float32))
    w["by_hash"] *= np.float32(0.1)
    w["o"] *= np.float32(0.1)
    return w


def train_steps(w: dict, m: dict, t: int, x, real, goal, use, of, steps: int, rate: float) -> int:
    """Steps that take every window once, in an order of their own."""
    for pick in np.array_split(np.random.default_rng(att.SEED + t).permutation(len(x)), steps):
        t += 1
        # each id is the goal of one window, as it is scored; the places before are read only
        att.step(w, m, t, x[pick], real[pick], goal[pick], use[pick], of, rate)
    return t


RUN = "bucket int, chunk long, hashes binary, counts binary"


def _shrink(x: np.ndarray) -> bytes:
    import zstandard

    return zstandard.ZstdCompressor(level=1).compress(x.tobytes())


def _grow(raw: bytes, kind: type) -> np.ndarray:
    import zstandard

    return np.frombuffer(zstandard.ZstdDecompressor().decompress(raw), kind)


def _count_runs(buckets: int):
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        edges = _edges(buckets)
        for b in batches:
            for r in b.to_pylist():
                (codes, size), h = _open_words(r["words"]), unsqueeze(r["names"])
                own = np.repeat(np.array([not held_out(i) for i in _doc_ids(r)]), size)
                c = np.bincount(codes[own], minlength=len(h)).astype(np.uint32)
                cut = np.concatenate([[0], np.searchsorted(h, edges), [len(h)]])
                k = np.flatnonzero(np.diff(cut))
                yield pa.RecordBatch.from_arrays(
                    [pa.array(k, pa.int32()), pa.array([r["chunk"]] * len(k), pa.int64()), pa.array([squeeze(h[cut[i] : cut[i + 1]]) for i in k], pa.binary()), pa.array([_shrink(c[cut[i] : cut[i + 1]]) for i in k], pa.binary())],
                    ["bucket", "chunk", "hashes", "counts"],
                )

    return run


def _total_runs(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Answers each run with its words' totals; a row without chunk has the range's sums."""
    held: dict[int, list] = {}
    for b in batches:
        for bucket, chunk, h, c in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist(), b.column(3).to_pylist(), strict=True):
            held.setdefault(bucket, []).append((chunk, unsqueeze(h), _grow(c, np.uint32)))
    for bucket in list(held):
        runs = held.pop(bucket)
        names, back = np.unique(np.concatenate([r[1] for r in runs]), return_inverse=True)
        total = np.bincount(back, np.concatenate([r[2] for r in runs]).astype(np.float64), len(names)).astype(np.int64)
        ends = np.cumsum([len(r[1]) for r in runs])
        out = [_shrink(total[back[e - len(r[1]) : e]].astype(np.uint64 if total.max() >> 32 else np.uint32)) for r, e in zip(runs, ends.tolist(), strict=True)]
        n = len(runs) + 1
        yield pa.RecordBatch.from_arrays(
            [pa.array([*[r[0] for r in runs], None], pa.int64()), pa.array([bucket] * n, pa.int32()), pa.array([*[8 if total.max() >> 32 else 4] * len(runs), 0], pa.int32()),
             pa.array([*out, b""], pa.binary()), pa.array([0] * len(runs) + [int(total.sum())], pa.int64()), pa.array([0] * len(runs) + [int((total > 0).sum())], pa.int64())],
            ["chunk", "bucket", "width", "totals", "n", "v"],
        )


def due(before: int, n: int) -> int:
    """Steps that ``n`` windows ask for after ``before`` others: one at the first of each ``SHARE`` batches."""
    share = SHARE * BATCH
    return -(-(before + n) // share) - -(-before // share)


def _refine(of: np.ndarray, start: bytes, vocab: int, before: dict[int, int]):
    """A task's training steps, through all of its windows."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        att.one_thread()
        w, m, t = att.unflatten(start), {}, 0
        for b in batches:
            for r in b.to_pylist():
                x, starts = _training_ids(r, vocab)
                passed, n = before[r["chunk"]], _n_windows(starts)
                for lo in range(0, len(n), 300):  # windows of some texts at a time
                    many = int(n[lo : lo + 300].sum())
                    if many:  # what is too small for a step of its own takes one all the same
                        a, real, goal, use, _ = att.windows(x[starts[lo] :], starts[lo : lo + 301] - starts[lo])
                        t = train_steps(w, m, t, a, real, goal, use, of, max(1, due(passed, many)), RATE)
                    passed += many
        if t:
            yield pa.RecordBatch.from_arrays([pa.array([0], pa.int32()), pa.array([t], pa.int64()), pa.array([att.flatten(w)], pa.binary())], ["level", "steps", "weights"])

    return run


def _average(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    steps, weights = 0, None
    for b in batches:
        for s, w in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
            w = np.frombuffer(w, np.float32).astype(np.float64) * s
            steps, weights = (s, w) if weights is None else (steps + s, weights + w)
    if steps:
        yield pa.RecordBatch.from_arrays([pa.array([0], pa.int32()), pa.array([steps], pa.int64()), pa.array([(weights / steps).astype(np.float32).tobytes()], pa.binary())], ["level", "steps", "weights"])


def fit(chunks: DataFrame, path: str) -> tuple[np.ndarray, InClass, bytes]:
    """Classes, probabilities in classes, weights."""
    encoder = WordEncoder.get(path)
    vocab, end = encoder.tokenizer.get_vocab_size(), encoder.tokenizer.token_to_id(END_TEXT)
    counts, before = id_counts(chunks, vocab)
    often = np.argsort(-counts, kind="stable")[:TOP]
    often = often[(counts[often] > 0) | (often == end)]
    rank = np.full(vocab, -1, np.int64)
    rank[often] = np.arange(len(often))
    of, pairs = classes(chunks, vocab, end, rank)
    start = att.flatten(first_weights(of, rank, pairs))
    kind = "level int, steps long, weights binary"
    got = chunks.select("chunk", "ids", "known", "extra").mapInArrow(_refine(of, start, vocab, before), kind)
    parts = n_buckets(chunks.sparkSession)
    while parts > 1:  # sums of sixteen at a time
        parts = -(-parts // 16)
        got = got.repartition(parts).mapInArrow(_average, kind)
    last = got.collect()
    return of, InClass(of, counts, rank, pairs), bytes(last[0]["weights"]) if last else start


def _model_scores(model):
    """The model's log10 probabilities of a chunk's texts, as an answer of bucket -1."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        att.one_thread()
        of, inside, weights = model.value
        w, (_, probs, many) = att.unflatten(weights), att.loops()
        for b in batches:
            for r in b.to_pylist():
                x, starts = _open(r["extra"], 1, len(of))
                x = x.astype(np.int64)
                near = np.zeros(len(x))
                near[1:] = inside(x[:-1], x[1:])
                near[starts[:-1]] = 0  # a text's opening end is no goal
                score = np.add.reduceat(near, starts[:-1])
                for lo in range(0, len(score), 200):  # windows of some texts at a time
                    a, real, goal, use, text = att.windows(x[starts[lo] :], starts[lo : lo + 201] - starts[lo])
                    for at in range(0, len(a), many):
                        s = slice(at, at + many)
                        p = probs(w, a[s], real[s], goal[s], of)
                        score += np.bincount(text[s] + lo, np.where(use[s], p, 0).sum(1, dtype=np.float64), len(score))
                yield pa.RecordBatch.from_arrays(
                    [pa.array([r["chunk"]], pa.int64()), pa.array([-1], pa.int32()), pa.array([8], pa.int32()), pa.array([(score / math.log(10)).tobytes()], pa.binary())],
                    ["chunk", "bucket", "width", "totals"],
                )

    return run


def _score(n_all: int, v_all: int):
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for r in b.to_pylist():
                ids = _doc_ids(r)
                codes, size = _open_words(r["words"])
                own, *parts = sorted(r["answers"], key=lambda a: a["bucket"])
                c = np.concatenate([_grow(a["totals"], np.uint32 if a["width"] == 4 else np.uint64) for a in parts]).astype(np.float64)
                cut = np.concatenate([[0], np.cumsum(size)[:-1]])
                base = np.add.reduceat(np.log10((c + 1) / (n_all + v_all + 1))[codes], cut)
                known = np.add.reduceat((c > 0).astype(np.int64)[codes], cut)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(ids, pa.int64()), pa.array([held_out(i) for i in ids]), pa.array(size), pa.array(known), pa.array([n_all] * len(ids), pa.int64()), pa.array(base), pa.array(np.frombuffer(own["totals"]))],
                    ["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"],
                )

    return run


def score_documents(docs: DataFrame, tokenizer_path: str, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """``doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score``."""
    spark = docs.sparkSession
    chunks = to_chunks(docs, id_col, text, "lm-chunks", _pack(tokenizer_path), TEXT_BYTES, ("extra", "words", "names"), keep=False)
    buckets = range_count(chunks, RANGE_CHUNKS)
    runs = chunks.select("chunk", "ids", "known", "words", "names").mapInArrow(_count_runs(buckets), RUN).repartition(buckets, "bucket")
    answers = spool(runs.mapInArrow(_total_runs, "chunk long, bucket int, width int, totals binary, n long, v long"), "lm-counts")
    n_all, v_all = answers.where("chunk is null").agg(F.coalesce(F.sum("n"), F.lit(0)), F.coalesce(F.sum("v"), F.lit(0))).first()
    model = spark.sparkContext.broadcast(fit(chunks, tokenizer_path))
    scored = chunks.select("chunk", "extra").mapInArrow(_model_scores(model), "chunk long, bucket int, width int, totals binary")
    told = answers.where("chunk is not null").select("chunk", "bucket", "width", "totals").unionByName(scored)
    back = told.groupBy("chunk").agg(F.collect_list(F.struct("bucket", "width", "totals")).alias("answers"))
    rows = chunks.select("chunk", "ids", "known", "words").join(back, "chunk").select("ids", "known", "words", "answers")
    kind = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"
    return rows.mapInArrow(_score(n_all, v_all), kind)
