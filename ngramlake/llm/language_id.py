"""Language identification with hyperdimensional profiles.

Every letter has a random vector of +1/-1.  The vector of a letter n-gram is the
product of its letters' vectors, each rotated by its place; a text's vector is
the sum of its n-grams' vectors, and a language's prototype the sum over its
training texts.  A text goes to the prototype of largest cosine.

Only letters count: others become one space, letters are lower-cased.  Training
adds, for every language, the counts of n-grams of all training rows, so nothing
is sampled; the prototypes that reach the driver are ``languages x dimensions``
numbers.  Prediction is one pass without a shuffle.

Cases: null text or text without a letter is ``und`` with score 0; without any
prototype all is ``und``; ties go to the language first in order; equal texts get
equal results; long texts are processed whole; an empty table gives no rows; a
null id is kept; further columns are not read.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

DIM, GRAM, SEED, SYMBOLS = 1024, 3, 11, 512
HELD_MODULUS, HELD = 4, 2
#: Cosine below which a text is like no language at all.
LEAST_SCORE = 0.02


@lru_cache(maxsize=1)
def _tables() -> tuple[np.ndarray, np.ndarray]:
    """Symbol of each code point (0: no letter) and the symbols' vectors by place."""
    code = np.zeros(0x110000, np.int16)
    for c in range(0x110000):
        if (s := chr(c)).isalpha():
            low = s.lower()
            o = ord(low[0])
            code[c] = o if o < 0x180 else 0x180 + o % (SYMBOLS - 0x180)
    base = np.random.default_rng(SEED).integers(0, 2, (SYMBOLS, DIM), np.int8) * np.int8(2) - np.int8(1)
    return code, np.stack([np.roll(base, GRAM - 1 - i, axis=1) for i in range(GRAM)])


def grams(text: str) -> tuple[np.ndarray, np.ndarray]:
    """Distinct n-gram codes of a text and their counts."""
    code, _ = _tables()
    if text.isascii():
        sym = code[np.frombuffer(text.encode(), np.uint8)]
    else:
        sym = code[np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)]
    letter = sym > 0
    keep = letter.copy()
    keep[1:] |= letter[:-1]
    sym = np.concatenate([[0], sym[keep], [0]])
    if not letter.any() or len(sym) < GRAM:
        return np.empty(0, np.int64), np.empty(0, np.int64)
    sym = sym.astype(np.int32)
    g = np.zeros(len(sym) - GRAM + 1, np.int32)
    for i in range(GRAM):
        g = g * SYMBOLS + sym[i : i + len(g)]
    return np.unique(g, return_counts=True)


def bundle(codes: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """The vector of counted n-grams."""
    _, place = _tables()
    out = np.zeros(DIM, np.float64)
    for at in range(0, len(codes), 2048):
        c = codes[at : at + 2048]
        v = place[GRAM - 1][c % SYMBOLS]
        for i in range(1, GRAM):
            v = v * place[GRAM - 1 - i][(c // SYMBOLS**i) % SYMBOLS]
        out += counts[at : at + 2048].astype(np.float32) @ v.astype(np.float32)
    return out


def _held(ids: list) -> list[bool]:
    return [zlib.crc32(str(i).encode()) % HELD_MODULUS == HELD if i is not None else False for i in ids]


def prototypes(docs: DataFrame, id_col: str = "doc_id", text: str = "text", lang: str = "lang") -> dict[str, np.ndarray]:
    """Prototype of each language among the rows that are not held out."""
    kind = "lang string, vec binary"

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[str, np.ndarray] = {}
        for b in batches:
            held: dict[str, list] = {}
            for t, name in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                held.setdefault(name, []).append(t)
            for name, texts in held.items():
                at, size = 0, 0
                for end in range(len(texts)):
                    size += len(texts[end])
                    if size > 1_000_000 or end == len(texts) - 1:  # texts end in a mark, so no n-gram spans two
                        v = bundle(*grams(" \0 ".join(texts[at : end + 1])))
                        total[name] = total.get(name, 0) + v
                        at, size = end + 1, 0
        if total:
            yield pa.RecordBatch.from_arrays([pa.array(list(total)), pa.array([v.tobytes() for v in total.values()], pa.binary())], ["lang", "vec"])

    train = docs.where(F.col(lang).isNotNull() & F.col(text).isNotNull() & (F.crc32(F.coalesce(F.col(id_col).cast("string"), F.lit("")).cast("binary")) % HELD_MODULUS != HELD))
    got = train.select(F.col(text).cast("string"), F.col(lang).cast("string")).mapInArrow(run, kind)

    def merge(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[str, np.ndarray] = {}
        for b in batches:
            for name, v in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                total[name] = total.get(name, 0) + np.frombuffer(v, np.float64)
        if total:
            yield pa.RecordBatch.from_arrays([pa.array(list(total)), pa.array([v.tobytes() for v in total.values()], pa.binary())], ["lang", "vec"])

    # a few vectors a task, added up by language in parallel before the driver sees them
    merged = got.repartition(8, "lang").mapInArrow(merge, kind).collect()
    return {r["lang"]: np.frombuffer(bytes(r["vec"]), np.float64) for r in sorted(merged, key=lambda r: r["lang"])}


def _classify(texts: list[str | None], names: list[str], unit: np.ndarray) -> tuple[list[str], list[float]]:
    lang, score = [], []
    for t in texts:
        codes, counts = grams(t) if t and names else ((), ())
        if not len(codes):
            lang.append("und")
            score.append(0.0)
            continue
        v = bundle(codes, counts)
        cos = unit @ v / max(float(np.sqrt((v * v).sum())), 1e-12)
        best = int(np.argmax(np.round(cos, 12)))
        lang.append(names[best])
        score.append(float(min(1.0, max(0.0, cos[best]))))
    return lang, score


def _units(profiles: dict[str, np.ndarray]) -> tuple[list[str], np.ndarray]:
    unit = [v / max(np.sqrt((v * v).sum()), 1e-12) for v in profiles.values()]
    return list(profiles), np.array(unit) if unit else np.zeros((0, DIM))


def predict(docs: DataFrame, profiles: dict[str, np.ndarray], id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """``doc_id, held_out, lang_pred, score`` of every row."""
    names, unit = _units(profiles)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            lang, score = _classify(b.column(1).to_pylist(), names, unit)
            held = _held(b.column(0).to_pylist())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(held, pa.bool_()), pa.array(lang, pa.string()), pa.array(score, pa.float64())], ["doc_id", "held_out", "lang_pred", "score"])

    rows = docs.select(F.col(id_col).cast("long"), F.col(text).cast("string"))
    return rows.mapInArrow(run, "doc_id long, held_out boolean, lang_pred string, score double")


def keep_identified(docs: DataFrame, profiles: dict[str, np.ndarray], text: str = "text", least: float = LEAST_SCORE) -> DataFrame:
    """The rows whose text has a letter and is at least that near to some prototype, unchanged."""
    names, unit = _units(profiles)
    at = docs.columns.index(text)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            lang, score = _classify(b.column(at).to_pylist(), names, unit)
            yield b.filter(pa.array([x != "und" and s >= least for x, s in zip(lang, score, strict=True)], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)


def identify(docs: DataFrame, id_col: str = "doc_id", text: str = "text", lang: str = "lang") -> DataFrame:
    """Train on the rows not held out, predict every row."""
    return predict(docs, prototypes(docs, id_col, text, lang), id_col, text)
