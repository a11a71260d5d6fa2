"""Ranking documents and comparing texts by soft matches of their windows."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ngramlake.functions.text import key_of
from ngramlake.operators import lookup, segments
from ngramlake.operators.index import WindowIndex


def query_grams(queries: DataFrame, n: int) -> DataFrame:
    """``query_id (of the gram), source_id, tokens, m``: each query's windows of ``n`` tokens."""
    size = F.size("tokens")
    own = F.transform(F.sequence(F.lit(0), F.greatest(size - n, F.lit(0))), lambda i: F.slice("tokens", i + 1, n))
    rows = queries.where(size > 0).select(F.col("query_id").alias("source_id"), F.explode(own).alias("tokens"))
    return rows.select(key_of(F.col("tokens")).alias("query_id"), "source_id", "tokens", F.size("tokens").alias("m"))


def soft_retrieve(grams: DataFrame, matches: DataFrame, index: WindowIndex | segments.SegmentIndex, n_docs: int, k: int = 1000) -> DataFrame:
    """``query_id, doc_id, score, rank``: for each gram its best match in the document
    times the gram's rarity (by documents that hold any match), summed."""
    occurrences = segments.occurrences if isinstance(index, segments.SegmentIndex) else lookup.occurrences
    places = occurrences(matches.select("key"), index).select("key", "doc_id").distinct()
    best = matches.join(places, "key").groupBy("query_id", "doc_id").agg(F.max("similarity").alias("best"))
    idf = best.groupBy("query_id").agg(F.log(1 + F.lit(float(n_docs)) / F.count("*")).alias("idf"))
    scored = grams.select("query_id", "source_id").join(best, "query_id").join(idf, "query_id").groupBy(F.col("source_id").alias("query_id"), "doc_id").agg(F.round(F.sum(F.col("best") * F.col("idf")), 6).alias("score"))
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "doc_id")
    return scored.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def text_classes(corpus: DataFrame) -> DataFrame:
    """``doc_id, rep``: each document and the least id among those of equal tokens."""
    h = corpus.select("doc_id", F.sha2(key_of(F.col("tokens")), 256).alias("h"))
    return h.join(h.groupBy("h").agg(F.min("doc_id").alias("rep")), "h").select("doc_id", "rep")


def class_pairs(members: DataFrame, grams: DataFrame) -> DataFrame:
    """``a, b, jaccard, score, n``: pairs of classes that share a gram, however many documents
    hold it, by distinct windows; the score averages both coverages.  ``grams`` are those of
    the representatives.  ``n`` counts the pairs of documents; a class with itself has
    ``a = b``.  Grams of the same documents are paired once, with their number."""
    sizes = grams.groupBy("doc_id").agg(F.count("*").alias("g"))
    classes = members.groupBy(F.col("rep").alias("doc_id")).agg(F.count("*").alias("m")).join(sizes, "doc_id")
    held = grams.groupBy("key").agg(F.sort_array(F.collect_list("doc_id")).alias("d")).where(F.size("d") > 1).groupBy("d").agg(F.count("*").alias("w"))
    left = held.select("d", "w", F.posexplode("d").alias("i", "a")).where(F.col("i") + 1 < F.size("d"))
    both = left.select("w", "a", F.explode(F.expr("slice(d, i + 2, size(d) - i - 1)")).alias("b")).groupBy("a", "b").agg(F.sum("w").alias("c"))
    side = lambda x: classes.select(F.col("doc_id").alias(x), F.col("g").alias(f"g{x}"), F.col("m").alias(f"m{x}"))
    x, c = both.join(side("a"), "a").join(side("b"), "b"), F.col("c")
    out = x.select("a", "b", F.round(c / (F.col("ga") + F.col("gb") - c), 6).alias("jaccard"), F.round((c / F.col("ga") + c / F.col("gb")) / 2, 6).alias("score"), (F.col("ma") * F.col("mb")).alias("n"))
    own = classes.where("m > 1").select(F.col("doc_id").alias("a"), F.col("doc_id").alias("b"), F.lit(1.0).alias("jaccard"), F.lit(1.0).alias("score"), F.expr("m * (m - 1) div 2").alias("n"))
    return out.unionByName(own)


def document_pairs(pairs: DataFrame, members: DataFrame) -> DataFrame:
    """``a, b, jaccard, score`` of documents, ``a < b``, from pairs of classes."""
    side = lambda x: members.select(F.col("doc_id").alias(x), F.col("rep").alias(f"r{x}"))
    rows = pairs.select(F.col("a").alias("rx"), F.col("b").alias("ry"), "jaccard", "score").join(side("x"), "rx").join(side("y"), "ry")
    rows = rows.where((F.col("rx") != F.col("ry")) | (F.col("x") < F.col("y")))
    return rows.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"), "jaccard", "score")


def soft_pair_score(pairs: DataFrame, near: DataFrame, theta: float, n: int = 5) -> DataFrame:
    """``pair_id, score`` of ``pair_id, a, b`` token arrays: mean over windows of each side of
    the best smooth similarity in the other, averaged; 0 below ``theta``.  Each pair is its own
    small corpus, so the join is on the pair."""
    from ngramlake.functions.similarity import cost, smooth_min

    def grams(col: str):
        return F.array_distinct(F.transform(F.sequence(F.lit(0), F.greatest(F.size(col) - n, F.lit(0))), lambda i: F.slice(col, i + 1, n)))

    x = pairs.select("pair_id", F.explode(grams("a")).alias("x"), F.col("b")).select("pair_id", "x", F.explode(grams("b")).alias("y")).where(F.size("x") == F.size("y"))
    slots = x.withColumn("_k", F.xxhash64("x", "y")).select("pair_id", "x", "y", F.posexplode(F.arrays_zip("x", "y")).alias("i", "t")).select("pair_id", "x", "y", F.col("t.x").alias("tok"), F.col("t.y").alias("nb"))
    scored = slots.join(near, ["tok", "nb"]).groupBy("pair_id", "x", "y").agg(F.count("*").alias("c"), F.sum(cost(F.col("cos"))).alias("s")).where(F.col("c") == F.size("x")).withColumn("sim", smooth_min(F.col("s"))).where(F.col("sim") >= theta)
    sides = []
    for side, col in (("x", "a"), ("y", "b")):
        best = scored.groupBy("pair_id", side).agg(F.max("sim").alias("sim")).groupBy("pair_id").agg(F.sum("sim").alias("s"))
        sides.append(pairs.select("pair_id", F.size(grams(col)).alias("n")).join(best, "pair_id", "left").select("pair_id", (F.coalesce("s", F.lit(0.0)) / F.col("n")).alias(side)))
    return sides[0].join(sides[1], "pair_id").select("pair_id", F.round((F.col("x") + F.col("y")) / 2, 6).alias("score"))
