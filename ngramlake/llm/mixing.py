"""Mixing sources to target weights, with DataFrame functions only.

Each source's share of ``budget`` times all words follows its weight, held at
``most`` times its own size; what is held back goes to the others by weight until
none is above: with sources ordered by the level at which they fill, that level
has a closed form, so one window over the sources' rows does it.

A document is taken ``floor(rate)`` times and once more with the probability of
the rate's fraction, decided by its hash (id and text).  Hashes are drawn under
several seeds; for each source the seed whose total comes nearest to its target
is used, so sources of few or very unequal documents come near theirs too.  The
totals under all seeds are one aggregation over (source, size, hash) rows, which
are written once and reread; the texts are counted in a single scan.

Cases: null text has size 0 and is taken 0 words; null source is a source of its
own, last in order; sources of size 0 have target 0; equal rows share a hash and
are treated alike; an empty table gives no rows; further columns are kept.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD_RE, spool, unused

WEIGHTS, BUDGET, MOST, SEEDS = (3, 1, 2), 1.5, 2.0, 32


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD_RE)), F.lit(0)).cast("long")


def source_targets(sizes: DataFrame, weights=WEIGHTS, budget: float = BUDGET, most: float = MOST) -> DataFrame:
    """``source, source_size, target`` from ``source, size`` rows."""
    s = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    order = Window.orderBy(F.col("source").asc_nulls_last())  # one row a source
    s = s.withColumn("w", F.element_at(F.array(*[F.lit(float(w)) for w in weights]), ((F.row_number().over(order) - 1) % len(weights) + 1).cast("int")))
    s = s.withColumn("cap", most * F.col("source_size")).withColumn("fills", F.col("cap") / F.col("w"))
    before = Window.orderBy("fills", F.col("source").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy()
    s = s.withColumn("full", F.coalesce(F.sum("cap").over(before), F.lit(0.0))).withColumn("w_full", F.coalesce(F.sum("w").over(before), F.lit(0.0)))
    s = s.withColumn("level", (budget * F.sum("source_size").over(whole) - F.col("full")) / (F.sum("w").over(whole) - F.col("w_full")))
    # the level that holds is the first one which its own source does not reach
    s = s.withColumn("held", F.coalesce(F.min(F.when(F.col("fills") >= F.col("level"), F.struct("fills", F.col("level").alias("v")))).over(whole)["v"], F.lit(float("inf"))))
    return s.select("source", "source_size", F.least("cap", F.col("w") * F.col("held")).alias("target"))


def _draw(seed: Column | int) -> Column:
    """Uniform in [0, 1) from the row's hash and a seed."""
    return F.pmod(F.xxhash64("h", F.lit(seed) if isinstance(seed, int) else seed), F.lit(1 << 40)) / float(1 << 40)


def plan(docs: DataFrame, text: str = "text", source: str = "source", id_col: str = "doc_id", **how) -> DataFrame:
    """``doc_id, size, source_size, target, copies, taken`` for each document row."""
    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(source).cast("string").alias("source"), word_count(F.col(text)).alias("size"), F.xxhash64(F.col(id_col), F.col(text)).alias("h"))
    rows = spool(rows, "mix")
    goal = source_targets(rows, **how)
    goal = goal.withColumn("rate", F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0))
    goal = goal.withColumn("often", F.floor("rate")).withColumn("extra", F.col("rate") - F.floor("rate"))
    given = goal.select(F.col("source").alias("s"), "source_size", "target", "often", "extra")
    with_goal = rows.join(given, rows.source.eqNullSafe(given.s))
    sums = [F.sum(F.when(_draw(k) < F.col("extra"), F.col("size")).otherwise(0)).alias(f"t{k}") for k in range(SEEDS)]
    tried = with_goal.groupBy("s", "target", "source_size", "often", "extra").agg(*sums)
    off = F.array_min(F.array(*[F.struct(F.abs(F.col("often") * F.col("source_size") + F.col(f"t{k}") - F.col("target")).alias("off"), F.lit(k).alias("seed")) for k in range(SEEDS)]))
    chosen = spool(tried.select("s", "target", "source_size", "often", "extra", off["seed"].alias("seed")), "mix-goal")
    copies = (F.col("often") + F.when(_draw(F.col("seed")) < F.col("extra"), 1).otherwise(0)).cast("int")
    out = rows.join(chosen, rows.source.eqNullSafe(chosen.s))
    return out.select("doc_id", "h", "size", "source_size", "target", copies.alias("copies"), (F.col("size") * copies).cast("long").alias("taken"))


def mixed_documents(docs: DataFrame, text: str = "text", source: str = "source", id_col: str = "doc_id", **how) -> DataFrame:
    """The mix itself: each row of ``docs`` as often as the plan takes it."""
    chosen = plan(docs, text, source, id_col, **how)
    chosen = chosen.where("copies > 0").groupBy(F.col("doc_id").alias("__id"), F.col("h").alias("__h")).agg(F.max("copies").alias("__copies"))
    h, i, n = unused(docs, "mix_hash", "mix_id", "mix_copies")
    chosen = chosen.select(F.col("__h").alias(h), F.col("__id").alias(i), F.col("__copies").alias(n))
    own = F.xxhash64(F.col(id_col), F.col(text))
    both = docs.join(chosen, F.col(id_col).eqNullSafe(F.col(i)) & (own == F.col(h)))
    return both.withColumn(n, F.explode(F.sequence(F.lit(1), n))).select(*[F.col(f"`{c}`") for c in docs.columns])
