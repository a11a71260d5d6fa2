"""Harmonic packing of token ids into sequences, independently on every worker.

A length ``t`` belongs to class ``j`` when ``capacity/(j+1) < t <= capacity/j``; a bin of
class ``j`` always takes exactly ``j`` documents.  Only documents longer than a capacity
are cut before they are classed, into whole capacities and a rest.

A full bin of class ``j`` leaves a gap of at most ``1/(j+1)`` of the capacity.  With
``fill`` the documents that come next close it, cut where the gap ends, and what is left
of a document goes to the class of its own length; without, the gap is padding, as in the
plain scheme.  At the end of a task the pieces in open bins are laid end to end, cut at
whole capacities, and the last rest into sequences whose lengths are powers of two, which
need no padding; without ``fill`` open bins are closed as they are.

No shuffle and no driver step: a task holds its open bins, below ``capacity`` tokens for
each class, and there are at most ``2 * sqrt(capacity)`` classes.

Cases: null text is empty (its document is the end id alone); a null id is kept; very
long texts are cut; equal rows are packed as often as they come; an empty table gives no
rows; further columns are not read.
"""

from __future__ import annotations

import zlib
from collections import deque
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import WordEncoder

CAPACITY, END_ID = 4096, 2
SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, class_size int"
_TYPES = [pa.int64()] * 7 + [pa.int32()]


class Packer:
    """Fills the bins of one worker; ``add`` and ``close`` give finished rows."""

    def __init__(self, first_id: int, capacity: int = CAPACITY, fill: bool = True):
        if capacity < 1 or capacity & (capacity - 1):
            raise ValueError("capacity must be a power of two")
        self.capacity, self.fill, self.next_id = capacity, fill, first_id
        self.open: dict[int, list[tuple]] = {}
        self.full: list[tuple] = []  # pieces of the one full bin whose gap is open
        self.full_class = self.gap = 0

    def _emit(self, pieces: list[tuple], size: int) -> Iterator[tuple]:
        at, sid = 0, self.next_id
        self.next_id += 1
        for doc, start, ids, total in pieces:
            n = len(ids) >> 2
            yield doc, start, n, zlib.crc32(ids), total, sid, at, size
            at += n

    def add(self, doc, ids: bytes) -> Iterator[tuple]:
        total, at, whole = len(ids) >> 2, 0, 4 * self.capacity
        if self.gap:
            at = min(self.gap, total)
            self.full.append((doc, 0, ids[: 4 * at], total))
            self.gap -= at
            if not self.gap:
                yield from self._emit(self.full, self.full_class)
        while total - at >= self.capacity:
            yield from self._emit([(doc, at, ids[4 * at : 4 * at + whole], total)], 1)
            at += self.capacity
        if at == total:
            return
        size = self.capacity // (total - at)
        held = self.open.setdefault(size, [])
        held.append((doc, at, ids[4 * at :], total))
        if len(held) == size:
            del self.open[size]
            gap = self.capacity - sum(len(p[2]) >> 2 for p in held)
            if gap and self.fill:
                self.full, self.full_class, self.gap = held, size, gap
            else:
                yield from self._emit(held, size)

    def close(self) -> Iterator[tuple]:
        rest = [self.full] * bool(self.gap) + [held for _, held in sorted(self.open.items())]
        if not self.fill:
            for held in rest:
                yield from self._emit(held, len(held))
            return
        pieces = deque(p for held in rest for p in held)
        left = sum(len(p[2]) >> 2 for p in pieces)
        while left:
            room = min(self.capacity, 1 << (left.bit_length() - 1))
            left -= room
            held = []
            while room:
                doc, start, ids, total = pieces.popleft()
                n = min(room, len(ids) >> 2)
                held.append((doc, start, ids[: 4 * n], total))
                room -= n
                if 4 * n < len(ids):
                    pieces.appendleft((doc, start + n, ids[4 * n :], total))
            yield from self._emit(held, len(held))


def padded(length: int, capacity: int = CAPACITY) -> int:
    """Length of a sequence with its padding: a power of two needs none."""
    return length if length & (length - 1) == 0 else capacity


def pack_documents(
    docs: DataFrame, tokenizer_path: str, id_col: str = "doc_id", text: str = "text",
    capacity: int = CAPACITY, end_id: int = END_ID, fill: bool = True,
) -> DataFrame:
    """One row for each piece: document, span, sequence and place in it."""
    end = np.array([end_id], "<u4").tobytes()

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        encoder = WordEncoder.get(tokenizer_path)
        packer = Packer(TaskContext.get().partitionId() << 33, capacity, fill)
        names = [f.split()[0] for f in SCHEMA.split(", ")]

        def batch(rows: list[tuple]) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), _TYPES, strict=True)], names)

        rows: list[tuple] = []
        for b in batches:
            texts = [t or b"" for t in b.column(1).cast(pa.binary()).to_pylist()]
            for doc, ids in zip(b.column(0).to_pylist(), encoder.encode_all(texts), strict=True):
                rows += packer.add(doc, ids + end)
                if len(rows) > 50_000:
                    yield batch(rows)
                    rows = []
        rows += packer.close()
        if rows:
            yield batch(rows)

    return docs.select(F.col(id_col).cast("long"), F.col(text).cast("string")).mapInArrow(run, SCHEMA)
