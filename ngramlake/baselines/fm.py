"""FM-index baseline: backward search over the Burrows-Wheeler column.

``bwt`` is the token before each sorted suffix, ``starts`` the suffixes that begin
with a smaller token, ``occ`` the count of a token before each block of ranks.  A
step reads two occurrence counts and the rest of two blocks for every pattern.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ngramlake.functions.text import SEP
from ngramlake.operators.vocab import token_rows
from ngramlake.sources.tables import spool

BLOCK = 1024


@dataclass
class FmIndex:
    bwt: DataFrame
    starts: DataFrame
    occ: DataFrame
    n: int


def build_fm(sa: DataFrame, corpus: DataFrame) -> FmIndex:
    """From a suffix array whose order covers the whole suffixes that are asked for.

    The array leaves out the empty suffixes at documents' ends; tokens at the ends
    have no row before them, and the first token of a document has none behind it.
    """
    rows = token_rows(corpus)
    before = rows.select("doc_id", (F.col("pos") + 1).alias("pos"), F.col("token").alias("prev"))
    bwt = spool(sa.join(before, ["doc_id", "pos"], "left").select("rank", (F.col("rank") / BLOCK).cast("long").alias("block"), "prev"), "bwt")
    counts = rows.groupBy("token").agg(F.count("*").alias("n"))
    first = sa.join(rows, ["doc_id", "pos"]).groupBy("token").agg(F.min("rank").alias("start"))
    starts = spool(first.join(counts, "token").select("token", "start", "n"), "starts")
    per = bwt.where("prev is not null").groupBy("prev", "block").agg(F.count("*").alias("c"))
    occ = spool(per.select(F.col("prev").alias("token"), "block", "c", F.coalesce(F.sum("c").over(Window.partitionBy("prev").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before")), "occ")
    return FmIndex(bwt, starts, occ, sa.count())


def _rank(state: DataFrame, fm: FmIndex, at: str, name: str) -> DataFrame:
    """Adds how often ``tok`` stands in the column before rank ``at``."""
    keys = state.select("tok", at).distinct().withColumn("_b", (F.col(at) / BLOCK).cast("long"))
    upto = keys.join(fm.occ.select(F.col("token").alias("tok"), "block", "c", "before"), "tok", "left").where("block < _b").groupBy("tok", at).agg(F.max(F.col("before") + F.col("c")).alias("_f"))
    inner = keys.join(fm.bwt.select(F.col("prev").alias("tok"), F.col("block").alias("_b"), "rank"), ["tok", "_b"]).where(F.col("rank") < F.col(at)).groupBy("tok", at).agg(F.count("*").alias("_i"))
    got = keys.join(upto, ["tok", at], "left").join(inner, ["tok", at], "left").select("tok", at, (F.coalesce("_f", F.lit(0)) + F.coalesce("_i", F.lit(0))).alias(name))
    return state.join(got, ["tok", at])


def fm_lookup(patterns: DataFrame, fm: FmIndex, longest: int) -> DataFrame:
    """``key, hits``: from the last token backwards, two ranks a step.

    Suffixes that are no document's end only: a document's last token precedes
    nothing, so its suffix is counted by its own start.
    """
    t = F.split("key", SEP)
    state = patterns.select("key").distinct().select("key", t.alias("t"), F.element_at(t, -1).alias("tok"))
    state = state.join(fm.starts.select(F.col("token").alias("tok"), "start", "n"), "tok", "left").select("key", "t", F.coalesce("start", F.lit(0)).alias("lo"), (F.coalesce("start", F.lit(0)) + F.coalesce("n", F.lit(0))).alias("hi"))
    for k in range(2, longest + 1):
        live = state.where(F.size("t") >= k).withColumn("tok", F.element_at("t", -k))
        ended = state.where(F.size("t") < k).select("key", "t", "lo", "hi")
        live = live.join(fm.starts.select(F.col("token").alias("tok"), "start", "n", ), "tok")
        live = _rank(_rank(live, fm, "lo", "a"), fm, "hi", "b")
        # suffixes (tok, end of document) come first among those of tok
        ends = fm.starts.select(F.col("token").alias("tok"), "n").join(fm.bwt.where("prev is not null").groupBy(F.col("prev").alias("tok")).agg(F.count("*").alias("inside")), "tok", "left").select("tok", (F.col("n") - F.coalesce("inside", F.lit(0))).alias("lone"))
        live = live.join(ends, "tok").select("key", "t", (F.col("start") + F.col("lone") + F.col("a")).alias("lo"), (F.col("start") + F.col("lone") + F.col("b")).alias("hi"))
        state = spool(live.unionByName(ended), "fm")
    known = state.select("key", F.greatest(F.lit(0), F.col("hi") - F.col("lo")).alias("hits"))
    return patterns.select("key").distinct().join(known, "key", "left").select("key", F.coalesce("hits", F.lit(0)).alias("hits"))
