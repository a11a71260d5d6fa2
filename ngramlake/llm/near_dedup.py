"""SimHash near-duplicates: pigeonring filtering, then connected components.

*Fingerprint.*  A bit is 1 if it is set in over half of the 64-bit hashes of a
text's word shingles, repeats included.

*Candidates.*  Cut 64 bits into a ring of ``segments``.  If two fingerprints
differ in at most ``bits`` bits, some segment starts a chain around the ring in
which every prefix of ``l`` segments holds at most ``l * bits / segments``
differences.  The prefixes whose budget is below one must agree, so they are an
equality key; the budgets of all longer prefixes are tested next, and only what
passes reaches the full Hamming check.  All distinct fingerprints take part, once
each, however many documents share them.

*Large groups.*  A key shared by more than ``small`` distinct fingerprints would
give a square of pairs.  Its fingerprints are linked another exact way: two
fingerprints lie within 2 bits if and only if they share one of the 65 strings
within 1 bit of each.  At most 65 fingerprints share such a string, so every
group is small, and a star in each group has the same components.  This holds for two
bits; other values of ``bits`` are refused.

Cases: null text counts as empty and has fingerprint zero, linked like any other;
fewer words than a shingle make one shingle of all; equal rows share a component;
null ids are kept and never name a component unless alone; an empty table gives
no rows; further columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import spool, unused

WORDS, BITS, SEGMENTS, SMALL, SEED = 3, 2, 8, 16, 42


def shingle_hashes(text: bytes, words: int = WORDS, seed: int = SEED) -> np.ndarray:
    """XXH64 of each shingle of a text, A-Z lower-cased."""
    from xxhash import xxh64_intdigest

    w = text.lower().split()
    if not w:
        return np.empty(0, np.uint64)
    line = b" ".join(w)
    if len(w) <= words:
        return np.array([xxh64_intdigest(line, seed)], np.uint64)
    ends = np.cumsum(np.fromiter(map(len, w), np.int64, len(w)) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])[: len(w) - words + 1].tolist()
    return np.array([xxh64_intdigest(line[s:e], seed) for s, e in zip(starts, ends[words - 1 :].tolist(), strict=True)], np.uint64)


def fingerprint(text: bytes, words: int = WORDS, seed: int = SEED) -> int:
    h = shingle_hashes(text, words, seed)
    if not len(h):
        return 0
    count = np.zeros(64, np.int64)
    for at in range(0, len(h), 32_768):
        part = h[at : at + 32_768].astype(">u8").view(np.uint8).reshape(-1, 8)
        count += np.unpackbits(part, axis=1).sum(0, dtype=np.int32)
    return int.from_bytes(np.packbits(count * 2 > len(h)).tobytes(), "big")


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text: str = "text", words: int = WORDS, seed: int = SEED, mark: str | None = None) -> DataFrame:
    """``doc_id, fp`` (fp: the 64 bits as a signed long), and ``mark``: a long column of that name, if given."""
    more = [F.col(mark).alias("mark")] if mark else []

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fps = np.array([fingerprint(t or b"", words, seed) for t in b.column(1).cast(pa.binary()).to_pylist()], np.uint64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fps.view(np.int64)), *b.columns[2:]], ["doc_id", "fp", "mark"][: b.num_columns])

    return docs.select(F.col(id_col).cast("long"), F.col(text).cast("string"), *more).mapInArrow(run, "doc_id long, fp long" + ", mark long" * bool(mark))


def _turn(x: Column, by: Column, segments: int) -> Column:
    """The ring read from segment ``by``."""
    width = 64 // segments
    left = by * width
    turned = F.call_function("shiftleft", x, left.cast("int")).bitwiseOR(F.call_function("shiftrightunsigned", x, (64 - left).cast("int")))
    return F.when(by == 0, x).otherwise(turned)


def _first(x: Column, n_bits: int) -> Column:
    return F.shiftrightunsigned(x, 64 - n_bits) if n_bits < 64 else x


def pigeonring_pairs(a: Column, b: Column, start: Column, bits: int, segments: int) -> Column:
    """Whether every prefix of the chain from ``start`` keeps its budget."""
    width, ring = 64 // segments, _turn(a.bitwiseXOR(b), start, segments)
    ok = F.lit(True)
    for n in range(1, segments + 1):
        ok = ok & (F.bit_count(_first(ring, n * width)) <= n * bits // segments)
    return ok


def links(fps: DataFrame, bits: int = BITS, segments: int = SEGMENTS, small: int = SMALL) -> DataFrame:
    """Pairs ``a < b`` of distinct fingerprints whose closure joins all within ``bits``."""
    if bits != 2:
        raise ValueError("large groups are split exactly for two bits")
    width = 64 // segments
    agree = -(-segments // bits) - 1  # segments whose budget is below one bit
    one = fps.select("fp").distinct()
    keys = one.select("fp", F.explode(F.array(*[F.struct(F.lit(i).alias("start"), _first(_turn(F.col("fp"), F.lit(i), segments), agree * width).alias("key")) for i in range(segments)])).alias("k"))
    keys = spool(keys.select("fp", "k.start", "k.key"), "ring-keys")
    sizes = keys.groupBy("start", "key").count().where("count > 1")
    few = keys.join(sizes.where(F.col("count") <= small).select("start", "key"), ["start", "key"]).groupBy("start", "key").agg(F.collect_list("fp").alias("g"))
    pair = F.flatten(F.transform("g", lambda a: F.transform(F.filter("g", lambda b: (a < b) & pigeonring_pairs(a, b, F.col("start"), bits, segments)), lambda b: F.struct(a.alias("a"), b.alias("b")))))
    near = few.select(F.explode(pair).alias("p")).select("p.a", "p.b").where(F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= bits)
    crowd = keys.join(sizes.where(F.col("count") > small).select("start", "key"), ["start", "key"], "left_semi").select("fp").distinct()
    ball = crowd.select("fp", F.explode(F.array(F.col("fp"), *[F.col("fp").bitwiseXOR(F.lit(np.int64(np.uint64(1 << i)).item())) for i in range(64)])).alias("z"))
    star = ball.groupBy("z").agg(F.collect_list("fp").alias("g")).where(F.size("g") > 1)  # at most 65
    star = star.select(F.array_min("g").alias("a"), F.explode("g").alias("b")).where("a < b")
    return near.unionByName(star).distinct()


def components(edges: DataFrame, rounds: int = 64) -> DataFrame:
    """``node, label``: the least node reachable; labels spread and jump until none changes."""
    both = spool(edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))), "links")
    label = spool(both.groupBy(F.col("a").alias("node")).agg(F.least(F.min("b"), F.first("a")).alias("label")), "labels")
    for _ in range(rounds):
        near = both.join(label.select(F.col("node").alias("b"), "label"), "b").groupBy(F.col("a").alias("node")).agg(F.min("label").alias("seen"))
        spread = label.join(near, "node").select("node", F.least("label", "seen").alias("label"), F.col("label").alias("old"))
        jump = spread.select(F.col("node").alias("label"), F.col("label").alias("far"))
        new = spool(spread.join(jump, "label", "left").select("node", F.least("label", F.coalesce("far", "label")).alias("label"), "old"), "labels")
        if new.where("label < old").isEmpty():
            break
        label = new.select("node", "label")
    else:
        raise RuntimeError("components did not settle")
    return new.select("node", "label")


def _classes(fps: DataFrame, bits: int, segments: int) -> DataFrame:
    """``fp, first, docs, label``: each distinct fingerprint, its least id, rows and component."""
    first = fps.groupBy("fp").agg(F.min("doc_id").alias("first"), F.count("*").alias("docs"))
    found = components(links(fps, bits, segments))
    named = first.join(found.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "first", "docs", F.coalesce("label", "fp").alias("label"))
    return spool(named, "simhash-classes")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text: str = "text", words: int = WORDS, bits: int = BITS, segments: int = SEGMENTS) -> DataFrame:
    """``doc_id, fp, fingerprint, component_id, group_size``; the size counts documents of a component."""
    fps = spool(fingerprints(docs, id_col, text, words), "simhash")
    named = _classes(fps, bits, segments)
    whole = named.groupBy("label").agg(F.min("first").alias("component_id"), F.sum("docs").alias("group_size"))
    out = fps.join(named.select("fp", "label").join(whole, "label").drop("label"), "fp")
    return out.select("doc_id", "fp", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id", "group_size")


def keep_one(docs: DataFrame, id_col: str = "doc_id", text: str = "text", words: int = WORDS, bits: int = BITS, segments: int = SEGMENTS) -> DataFrame:
    """``docs`` with one row of each component: that of the least id (null ids last), by the
    text's hash among rows that share it.  A row is known by its id and its text, for ids
    may be null or repeat over different texts."""
    name, mark = unused(docs, "stay", "stay_text")
    of_text = F.xxhash64(F.coalesce(F.col(f"`{text}`").cast("string"), F.lit("")))
    fps = spool(fingerprints(docs.withColumn(mark, of_text), id_col, text, words, mark=mark), "simhash")
    named = _classes(fps, bits, segments).select("fp", "label")
    least = F.min(F.struct(F.col("doc_id").isNull().alias("lacks"), "doc_id", "mark")).alias("least")
    stay = fps.join(named, "fp").groupBy("label").agg(least).select(F.col("least.doc_id").alias(name), F.col("least.mark").alias("mark"))
    stay = stay.withColumnRenamed("mark", mark)
    rows = docs.withColumn(mark, of_text).alias("rows").join(stay.alias("one"), F.col(f"rows.`{id_col}`").cast("long").eqNullSafe(F.col(f"one.{name}")) & (F.col(f"rows.{mark}") == F.col(f"one.{mark}")), "left_semi")
    return rows.dropDuplicates([id_col, mark]).drop(mark)
