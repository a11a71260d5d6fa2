"""Contamination of test items by a corpus: share of an item's windows that it holds."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ngramlake.functions.text import SEP, key_of

SPAN, SIMILAR, DIRTY = 10, 0.6, 0.8


def item_windows(items: DataFrame, span: int = SPAN) -> DataFrame:
    """``item_id, key, n``: every window of an item; a short item is one window."""
    size = F.size("tokens")
    own = F.transform(F.sequence(F.lit(0), F.greatest(size - span, F.lit(0))), lambda i: key_of(F.slice("tokens", i + 1, span)))
    return items.where(size > 0).select("item_id", F.explode(own).alias("key"))


def character_windows(texts: DataFrame, id_col: str, span: int = 50) -> DataFrame:
    """``id_col, key`` of every window of characters; a shorter text is one window, an empty one none."""
    own = F.transform(F.sequence(F.lit(1), F.greatest(F.length("text") - span + 1, F.lit(1))), lambda i: F.substring(F.col("text"), i, F.lit(span)))
    return texts.where(F.length("text") > 0).select(id_col, F.explode(own).alias("key"))


def character_coverage(items: DataFrame, docs: DataFrame, span: int = 50) -> DataFrame:
    """``item_id, windows, eta, dirty`` by exact windows of characters.  Windows of
    documents meet those of items by a semi-join, before anything is kept."""
    w = character_windows(items, "item_id", span)
    asked = w.select("key").distinct()
    held = character_windows(docs, "doc_id", span).select("key").join(asked, "key", "left_semi").distinct()
    return coverage(w, held)


def exact_matches(windows: DataFrame, find: Callable[[DataFrame], DataFrame]) -> DataFrame:
    return find(windows.select("key").distinct()).select("key")


def soft_matches(windows: DataFrame, exact: DataFrame, search: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """Windows with a similar pattern: exact ones, then the others by soft search."""
    rest = windows.select("key").distinct().join(exact, "key", "left_anti")
    t = F.split("key", SEP)
    found = search(rest.select(F.col("key").alias("query_id"), t.alias("tokens"), F.size(t).alias("m")))
    return exact.unionByName(found.select(F.col("query_id").alias("key")).distinct())


def coverage(windows: DataFrame, matched: DataFrame, dirty: float = DIRTY) -> DataFrame:
    """``item_id, windows, eta, dirty``."""
    hit = windows.join(matched.select("key", F.lit(1).alias("hit")), "key", "left")
    out = hit.groupBy("item_id").agg(F.count("*").alias("windows"), F.round(F.avg(F.coalesce("hit", F.lit(0))), 6).alias("eta"))
    return out.withColumn("dirty", F.col("eta") >= dirty)


def gain(soft: DataFrame, exact: DataFrame) -> DataFrame:
    """Items that only the soft arm marks."""
    return soft.where("dirty").join(exact.where("dirty"), "item_id", "left_anti")


def classify(extra: DataFrame) -> DataFrame:
    """Class of soft-only matches from ``item_id, q, p`` token arrays of equal windows:
    ``exact`` if no token differs, ``template`` if all differing tokens are numbers on both
    sides, else ``semantic``."""
    pairs = F.filter(F.arrays_zip("q", "p"), lambda x: ~x.q.eqNullSafe(x.p))
    number = lambda c: c.rlike("^[0-9]+$")
    return extra.withColumn("class", F.when(F.size(pairs) == 0, "exact").when(F.forall(pairs, lambda x: F.coalesce(number(x.q) & number(x.p), F.lit(False))), "template").otherwise("semantic"))


def report(flags: DataFrame) -> DataFrame:
    """Rates over ``item_id, exact, soft, truth`` with totals by grouping sets."""
    return flags.rollup("truth").agg(F.count("*").alias("items"), F.sum(F.col("exact").cast("int")).alias("exact"), F.sum((F.col("soft") & ~F.col("exact")).cast("int")).alias("extra"))


def evidence(patterns: DataFrame, occurrences: DataFrame, corpus: DataFrame, after: int = 50) -> DataFrame:
    """First place of each pattern and what follows it."""
    first = occurrences.groupBy("key").agg(F.min(F.struct("doc_id", "pos")).alias("at"))
    rows = patterns.join(first, "key").select("key", "at.doc_id", "at.pos", F.size(F.split("key", SEP)).alias("n"))
    return rows.join(corpus.select("doc_id", "tokens"), "doc_id").select("key", "doc_id", "pos", F.array_join(F.slice("tokens", F.col("pos") + 1, F.col("n") + after), " ").alias("passage"))
