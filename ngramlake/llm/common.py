"""Shared parts of the training-data operators: spooling, chunk rows, word ids.

*Chunk rows.*  Operators that visit every text twice keep the texts as rows of
about ``CHUNK_BYTES`` raw bytes (``chunk``, packed ids and lengths, zstd
payload), written once to the shared folder.  A chunk is rebuilt by Spark from
its input split if an executor is lost while it is written; afterwards the
Parquet table is the lineage.
"""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
import zipfile
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

CHUNK_BYTES = 4 << 20
#: Entries a Python worker keeps of its word cache before it starts afresh.
CACHE_WORDS = 200_000
WORD_RE = r"[^\x20\x09-\x0D]+"


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The shared folder for cut lineage; a temporary one only where none is set and all
    tasks run on this machine."""
    at = spark.conf.get("spark.checkpoint.dir", None)
    if not at:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        at = getattr(spark, "_llm_shared", None)
        if not at:
            at = spark._llm_shared = "file://" + tempfile.mkdtemp(prefix="llm-shared-")
    return at


def spool(df: DataFrame, name: str, compression: str = "zstd") -> DataFrame:
    """Write ``df`` to the shared folder and read it back: lineage ends here.

    The files are deleted when the application ends.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.option("compression", compression).parquet(path)
    jvm = spark._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(where)
    return spark.read.schema(df.schema).parquet(path)


def ship(spark: SparkSession) -> None:
    """Give this package to executors that lack it, once per application."""
    sc = spark.sparkContext
    if getattr(sc, "_llm_shipped", False):
        return
    root = Path(__file__).resolve().parents[1]
    if not root.is_dir():
        return
    at = Path(tempfile.mkdtemp(prefix="llm-ship-"))
    name = at / f"{root.name}-{uuid.uuid4().hex[:8]}.zip"
    with zipfile.ZipFile(name, "w") as z:
        for p in sorted(root.rglob("*.py")):
            z.write(p, p.relative_to(root.parent))
    sc.addPyFile(str(name))
    atexit.register(shutil.rmtree, at, ignore_errors=True)  # executors fetch it while the application runs
    sc._llm_shipped = True


def unused(df: DataFrame, *names: str) -> list[str]:
    """The names with as many underscores in front as keep them apart from ``df``'s."""
    have = {c.lower() for c in df.columns}
    out = []
    for n in names:
        while n.lower() in have:
            n = "_" + n
        out.append(n)
    return out


def n_buckets(spark: SparkSession, least: int = 12) -> int:
    """Exchange width: Spark's own setting, ``least`` if that is smaller."""
    return max(least, int(spark.conf.get("spark.sql.shuffle.partitions", "200")))


def range_count(chunks: DataFrame, chunks_each: int) -> int:
    """Ranges of an exchange between chunks: one for ``chunks_each`` chunks, so a range does
    not grow with the data, and no fewer than Spark's own width."""
    return max(n_buckets(chunks.sparkSession), -(-chunks.count() // chunks_each))


# ------------------------------------------------------------------ chunk rows
CHUNK_SCHEMA = "chunk long, n int, ids binary, known binary, lens binary, payload binary"


def _chunk_batches(batches, extra=None, size=CHUNK_BYTES, names=(), keep=True):
    import zstandard
    from pyspark import TaskContext

    pid, seq = TaskContext.get().partitionId(), 0
    ids: list = []
    texts: list[bytes] = []
    total = 0

    def flush():
        nonlocal ids, texts, total, seq
        lens = np.fromiter(map(len, texts), np.int64, len(texts))
        known = np.fromiter((i is not None for i in ids), np.uint8, len(ids))
        row = pa.RecordBatch.from_pydict(
            {
                "chunk": pa.array([(pid << 32) | seq], pa.int64()),
                "n": pa.array([len(ids)], pa.int32()),
                "ids": [np.array([0 if i is None else i for i in ids], np.int64).tobytes()],
                "known": [known.tobytes()],
                "lens": [lens.tobytes()],
                "payload": [zstandard.ZstdCompressor(level=3).compress(b"".join(texts) if keep else b"")],
            }
            | ({n: [x] for n, x in zip(names, extra(texts), strict=True)} if extra else {})
        )
        ids, texts, total, seq = [], [], 0, seq + 1
        return row

    for b in batches:
        for i, t in zip(b.column(0).to_pylist(), b.column(1).cast(pa.binary()).to_pylist(), strict=True):
            t = t or b""
            ids.append(i)
            texts.append(t)
            total += len(t)
            if total >= size or len(ids) >= 20_000:
                yield flush()
    if ids:
        yield flush()
    getattr(extra, "done", lambda: None)()


def to_chunks(docs: DataFrame, id_col: str, text: str, name: str, extra=None, size: int = CHUNK_BYTES, names: tuple[str, ...] = (), keep: bool = True) -> DataFrame:
    """Spool ``(id, text)`` as chunk rows of about ``size`` bytes; null text is empty, null ids are kept.

    ``extra`` makes the binary columns ``names`` from a chunk's texts, and its ``done``, if it
    has one, is called when a task ends; without ``keep`` the texts themselves are left out."""
    rows = docs.select(F.col(id_col).cast("long"), F.col(text).cast("string"))
    kind = ", ".join([CHUNK_SCHEMA, *[f"{n} binary" for n in names]])
    return spool(rows.mapInArrow(lambda b: _chunk_batches(b, extra, size, names, keep), kind), name, "uncompressed")


def open_chunk(n: int, ids: bytes, known: bytes, lens: bytes, payload: bytes):
    """``(ids list with None, texts list of bytes)`` of one chunk row."""
    import zstandard

    sizes = np.frombuffer(lens, np.int64)
    raw = zstandard.ZstdDecompressor().decompress(payload, max_output_size=max(1, int(sizes.sum())))
    ends = np.cumsum(sizes)
    got = [i if k else None for i, k in zip(np.frombuffer(ids, np.int64).tolist(), np.frombuffer(known, np.uint8), strict=True)]
    return got, [raw[e - s : e] for s, e in zip(sizes.tolist(), ends.tolist(), strict=True)]


# ------------------------------------------------------------------- word ids
_MARKS = ".,;:!?#$%&*()-"


class WordEncoder:
    """Ids of white-space separated chunks under the word-end BPE vocabulary.

    The vocabulary drops white space and never lets a token span it, so a text's
    ids are those of its chunks in order.  Chunks of letters below U+0250 with
    trailing marks are looked up as a word and a run of marks; the words that a
    batch lacks go to the BPE model together.  Any other chunk goes through the
    whole tokenizer.  One instance lives in each Python worker; its cache is bounded.
    """

    _own: dict[str, WordEncoder] = {}

    @classmethod
    def get(cls, path: str) -> WordEncoder:
        if path not in cls._own:
            cls._own[path] = cls(path)
        return cls._own[path]

    def __init__(self, path: str):
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer, pre_tokenizers

        self.tokenizer = Tokenizer.from_file(path)
        self.plain = Tokenizer(self.tokenizer.model)
        self.plain.pre_tokenizer = pre_tokenizers.WhitespaceSplit()
        vocab = self.tokenizer.get_vocab()
        self.last = np.zeros(max(vocab.values()) + 1, bool)
        self.last[[i for t, i in vocab.items() if t.endswith("</w>")]] = True
        self.cache: dict[bytes, bytes] = {}
        self.words: dict[str, bytes] = {}
        printable = [*range(33, 127), *range(161, 173), *range(174, 256)]
        spare = iter(range(256, 512))
        self.as_char = [chr(b if b in printable else next(spare)) for b in range(256)]

    def _learn(self, words: list[str]) -> None:
        """Ids of words whose characters the vocabulary maps one by one."""
        for at in range(0, len(words), 20_000):
            part = words[at : at + 20_000]
            line = " ".join(part)
            if not line.isascii():
                line = " ".join(w if w.isascii() else "".join([self.as_char[b] for b in w.encode()]) for w in part)
            ids = np.array(self.plain.encode_batch_fast([line], add_special_tokens=False)[0].ids, "<u4")
            ends = (np.flatnonzero(self.last[ids]) + 1) * 4
            if len(ends) != len(part):
                raise RuntimeError("the vocabulary has no word ends")
            raw, start = ids.tobytes(), 0
            for w, end in zip(part, ends.tolist(), strict=True):
                self.words[w] = raw[start:end]
                start = end

    def _fill(self, missing: list[bytes]) -> None:
        words, cache = self.words, self.cache
        text = b"\n".join(missing).decode("utf-8", "replace")  # no chunk holds white space
        odd = {} if text.isascii() else {k for k, s in enumerate(text.split("\n")) if not s.isascii() and (max(s) >= "ɐ" or "İ" in s)}
        lows = text.lower().split("\n") if missing else []
        stems = [s.rstrip(_MARKS) for s in lows]
        for k, w in enumerate(stems):
            if k in odd or (w and not w.isalpha()):
                cache[missing[k]] = np.array(self.tokenizer.encode(missing[k].decode("utf-8", "replace"), add_special_tokens=False).ids, "<u4").tobytes()
                stems[k] = lows[k] = ""
        marks = [s[len(w) :] for s, w in zip(lows, stems, strict=True)]
        self._learn([w for w in {*stems, *marks} if w and w not in words])
        words[""] = b""
        for c, s, w, m in zip(missing, lows, stems, marks, strict=True):
            if s:
                cache[c] = words[w] + words[m]

    def encode_all(self, texts: list[bytes]) -> list[bytes]:
        """Little-endian unsigned 32-bit ids of each UTF-8 text."""
        if len(self.cache) > CACHE_WORDS:
            self.cache.clear()
            self.words.clear()
        out: list = []
        get = self.cache.get
        lack: list[tuple[int, list[bytes], list]] = []
        missing: list[bytes] = []

        def fill() -> None:
            self._fill(list(set(missing)))
            for k, chunks, got in lack:
                out[k] = b"".join([g or get(c) for c, g in zip(chunks, got, strict=True)])
            missing.clear()
            lack.clear()

        for t in texts:
            chunks = t.split()
            got = list(map(get, chunks))
            if None in got:
                lack.append((len(out), chunks, got))
                missing += [c for c, g in zip(chunks, got, strict=True) if g is None]
                out.append(None)
                if len(missing) > 50_000:
                    fill()
            else:
                out.append(b"".join(got))
        fill()
        return out

    def encode_words(self, words: list[bytes]) -> list[bytes]:
        """The same of distinct single words, which the cache does not keep: the caller does."""
        for at in range(0, len(words), 50_000):
            self._fill(words[at : at + 50_000])
        return list(map(self.cache.pop, words))

    def encode(self, text: bytes) -> bytes:
        return self.encode_all([text])[0]
