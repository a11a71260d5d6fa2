"""Vocabulary, frequencies and n-gram sets."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ngramlake.functions.text import key_of


def token_rows(corpus: DataFrame) -> DataFrame:
    return corpus.select("doc_id", F.posexplode("tokens").alias("pos", "token"))


def token_counts(corpus: DataFrame, min_freq: int = 1) -> DataFrame:
    """``token, freq``: one shuffle with map-side combine."""
    return corpus.select(F.explode("tokens").alias("token")).groupBy("token").agg(F.count("*").alias("freq")).where(F.col("freq") >= min_freq)


def build_vocab(corpus: DataFrame, min_freq: int = 1) -> DataFrame:
    """``token_id, token, freq, p, surprisal``: ids by falling frequency, then token.

    Ranks come from a range sort: a row's place in its partition plus the sizes of
    the partitions before, so no window runs over the whole vocabulary.
    """
    counts = token_counts(corpus, min_freq)
    total = counts.agg(F.sum("freq").alias("total"))
    ranked = add_rank(counts, [F.desc("freq"), F.col("token")], "token_id")
    return ranked.join(F.broadcast(total)).select("token_id", "token", "freq", (F.col("freq") / F.col("total")).alias("p"), (-F.log(F.col("freq") / F.col("total"))).alias("surprisal"))


def add_rank(df: DataFrame, order: list, name: str = "rank") -> DataFrame:
    """0-based global rank; the sorted rows are written once, then numbered."""
    from ngramlake.sources.tables import spool

    where = F.monotonically_increasing_id()
    rows = spool(df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_at", where), "ranked")
    part, idx = F.shiftright("_at", 33), F.col("_at").bitwiseAND((1 << 33) - 1)
    sizes = rows.groupBy(part.alias("_part")).agg(F.count("*").alias("_n"))  # one row a partition
    before = F.coalesce(F.sum("_n").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return rows.withColumn("_part", part).join(F.broadcast(sizes.select("_part", before.alias("_before"))), "_part").withColumn(name, F.col("_before") + idx).drop("_part", "_before", "_at")


def ngrams(corpus: DataFrame, n: int) -> DataFrame:
    """``doc_id, pos, key`` of all whole n-token windows."""
    size = F.size("tokens")
    own = F.transform(F.sequence(F.lit(0), size - n), lambda i: key_of(F.slice("tokens", i + 1, n)))
    return corpus.where(size >= n).select("doc_id", F.posexplode(own).alias("pos", "key"))


def ngram_counts(corpus: DataFrame, n: int) -> DataFrame:
    return ngrams(corpus, n).groupBy("key").agg(F.count("*").alias("hits"))


def ngram_sets(corpus: DataFrame, most: int) -> DataFrame:
    """``n, key`` of all distinct n-grams for n up to ``most``, in one shuffle."""
    size = F.size("tokens")
    sizes = F.transform(F.sequence(F.lit(1), F.least(F.lit(most), size)), lambda n: F.struct(n.alias("n"), F.transform(F.sequence(F.lit(0), size - n), lambda i: key_of(F.slice("tokens", i + 1, n))).alias("keys")))
    rows = corpus.where(size > 0).select(F.explode(sizes).alias("g")).select("g.n", F.explode("g.keys").alias("key"))
    return rows.distinct()


def frequent_kgrams(corpus: DataFrame, top_words: int, k: int) -> DataFrame:
    """``key`` of the k-grams that occur and hold only the ``top_words`` most frequent tokens."""
    top = token_counts(corpus).orderBy(F.desc("freq"), "token").limit(top_words).select("token")
    rows = ngrams(corpus, k).select("key").distinct().withColumn("_t", F.split("key", "\x01"))
    for i in range(k):
        rows = rows.join(F.broadcast(top.withColumnRenamed("token", f"_t{i}")), F.col("_t")[i] == F.col(f"_t{i}"), "left_semi")
    return rows.select("key")
