"""Corpus laws, lookup counts and their bound, quality and latency measures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


# ------------------------------------------------------------------ corpus laws
def zipf_fit(counts: DataFrame, top: int = 2000) -> DataFrame:
    """``alpha, r2`` of log frequency on log rank over the most frequent tokens (a top-k)."""
    best = counts.orderBy(F.desc("freq"), "token").limit(top)
    ranked = best.withColumn("rank", F.row_number().over(Window.orderBy(F.desc("freq"), "token")))  # at most ``top`` rows
    x, y = F.log("rank"), F.log("freq")
    return ranked.agg(F.round(-F.regr_slope(y, x), 6).alias("alpha"), F.round(F.regr_r2(y, x), 6).alias("r2"))


def heaps_points(tokens_by_step: DataFrame) -> DataFrame:
    """``step, tokens, types``: tokens read and types met up to each step.

    A type counts at the first step that has it, so one aggregation and a window
    over the steps do.  Input: ``step, token``.
    """
    first = tokens_by_step.groupBy("token").agg(F.min("step").alias("step"), F.count("*").alias("n"))
    per = tokens_by_step.groupBy("step").agg(F.count("*").alias("n")).join(first.groupBy("step").agg(F.count("*").alias("new")), "step", "left")
    w = Window.orderBy("step").rowsBetween(Window.unboundedPreceding, 0)  # one row a step
    return per.select("step", F.sum("n").over(w).alias("tokens"), F.sum(F.coalesce("new", F.lit(0))).over(w).alias("types"))


def heaps_fit(points: DataFrame) -> DataFrame:
    """``exponent, r2`` of log types on log tokens."""
    x, y = F.log("tokens"), F.log("types")
    return points.agg(F.round(F.regr_slope(y, x), 6).alias("exponent"), F.round(F.regr_r2(y, x), 6).alias("r2"))


# ------------------------------------------------------------- lookups and bound
def trace_counts(trace: list) -> DataFrame:
    """``query_id, step, candidates, kept`` from the frames a traced search left."""
    out = None
    for i, cand, kept in trace:
        p = cand.where(F.col("key") != "").groupBy("query_id").agg(F.countDistinct("key").alias("candidates"))
        c = kept.where(F.col("key") != "").groupBy("query_id").agg(F.countDistinct("key").alias("kept"))
        part = p.join(c, "query_id", "left").select("query_id", F.lit(i).alias("step"), "candidates", F.coalesce("kept", F.lit(0)).alias("kept"))
        out = part if out is None else out.unionByName(part)
    return out


def lookup_totals(steps: DataFrame) -> DataFrame:
    """``query_id, lookups``: the sum of candidates over the steps."""
    return steps.groupBy("query_id").agg(F.sum("candidates").alias("lookups"))


def geometric_mean(x: Column) -> Column:
    return F.exp(F.avg(F.log(x)))


def growth_bound(steps: DataFrame, queries: DataFrame, m: int) -> DataFrame:
    """Fitted constants and the bound: ``a, k, r, lookups, bound``.

    ``a`` is the largest ratio of mean candidates to the mean of those kept a step
    before; ``k * r**i`` lies above the mean kept at every step, with ``r`` from a
    fit of its logarithm.
    """
    n = queries.agg(F.count("*").alias("queries"))
    per = steps.groupBy("step").agg(F.sum("candidates").alias("p"), F.sum("kept").alias("c")).join(F.broadcast(n))
    per = per.select("step", (F.col("p") / F.col("queries")).alias("p"), (F.col("c") / F.col("queries")).alias("c"))
    before = F.coalesce(F.lag("c").over(Window.orderBy("step")), F.lit(1.0))  # one row a step
    rows = per.withColumn("before", before)
    start = rows.agg(F.max(F.when(F.col("before") > 0, F.col("p") / F.col("before"))).alias("a"), F.exp(F.regr_slope(F.log("c"), F.col("step"))).alias("r"), F.sum("p").alias("lookups"))
    k = rows.join(F.broadcast(start)).groupBy("a", "r", "lookups").agg(F.greatest(F.lit(1.0), F.max(F.when(F.col("c") > 0, F.col("c") / F.pow("r", "step")))).alias("k"))
    series = F.when(F.abs(F.col("r") - 1) < 1e-9, F.lit(float(m))).otherwise((1 - F.pow("r", F.lit(m))) / (1 - F.col("r")))
    return k.select(F.round("a", 6).alias("a"), F.round("k", 6).alias("k"), F.round("r", 6).alias("r"), F.round("lookups", 6).alias("lookups"), F.round(F.col("a") * F.col("k") * series, 6).alias("bound"))


def growth_per_token(totals: DataFrame, *by: str) -> DataFrame:
    """Factor per query token from ``m, lookups``: exponent of a log-linear fit of the
    geometric means over queries."""
    per = totals.groupBy(*by, "m").agg(geometric_mean(F.col("lookups")).alias("t"))
    return per.groupBy(*by).agg(F.round(F.exp(F.regr_slope(F.log("t"), F.col("m"))), 6).alias("factor"))


def lookups_by_length(steps: DataFrame, near: DataFrame, queries: DataFrame, longest: int) -> DataFrame:
    """``pruning, query_id, m, lookups`` of each query cut to its first ``m`` tokens: with pruning
    the candidates of all steps up to ``m``; without, every combination of neighbours."""
    w = Window.partitionBy("query_id").rowsBetween(Window.unboundedPreceding, 0)  # a query's steps
    upto = steps.select("query_id", "candidates", F.explode(F.sequence(F.col("step"), F.lit(longest))).alias("m"))
    pruned = upto.groupBy("query_id", "m").agg(F.sum("candidates").cast("double").alias("lookups")).select(F.lit("iterative").alias("pruning"), "query_id", "m", "lookups")
    slots = queries.select("query_id", F.posexplode("tokens").alias("i", "tok")).join(near.groupBy("tok").agg(F.count("*").alias("n")), "tok")
    every = slots.select(F.lit("none").alias("pruning"), "query_id", (F.col("i") + 1).alias("m"), F.exp(F.sum(F.log("n")).over(w.orderBy("i"))).alias("lookups"))
    return pruned.unionByName(every)


def sampling_model(near: DataFrame, queries: DataFrame, gram_totals: DataFrame, vocabulary: int, kept: DataFrame) -> DataFrame:
    """``step, expected, kept``: similar patterns that would occur if n-grams were drawn
    uniformly, beside those that do; language keeps many more as patterns grow."""
    slots = queries.select("query_id", F.posexplode("tokens").alias("i", "tok")).join(near.groupBy("tok").agg(F.count("*").alias("n")), "tok")
    w = Window.partitionBy("query_id").orderBy("i").rowsBetween(Window.unboundedPreceding, 0)
    sims = slots.withColumn("sim", F.exp(F.sum(F.log("n")).over(w))).groupBy((F.col("i") + 1).alias("step")).agg(F.avg("sim").alias("sim"))
    share = gram_totals.select(F.col("n").alias("step"), (F.col("types") / F.pow(F.lit(float(vocabulary)), F.col("n"))).alias("share"))
    return sims.join(share, "step").join(kept, "step").select("step", (F.col("sim") * F.col("share")).alias("expected"), "kept")


# ------------------------------------------------------------- quality measures
def precision_at(ranked: DataFrame, truth: DataFrame, k: int, queries: DataFrame) -> DataFrame:
    """``query_id, value``: share of the first ``k`` that are relevant."""
    hit = ranked.where(F.col("rank") <= k).join(truth, ["query_id", "doc_id"], "left_semi").groupBy("query_id").agg(F.count("*").alias("h"))
    return queries.select("query_id").join(hit, "query_id", "left").select("query_id", F.round(F.coalesce("h", F.lit(0)) / k, 6).alias("value"))


def recall_at(ranked: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """``query_id, value``: share of the relevant among the first ``k``; queries with any."""
    all_ = truth.groupBy("query_id").agg(F.count("*").alias("n"))
    hit = ranked.where(F.col("rank") <= k).join(truth, ["query_id", "doc_id"], "left_semi").groupBy("query_id").agg(F.count("*").alias("h"))
    return all_.join(hit, "query_id", "left").select("query_id", F.round(F.coalesce("h", F.lit(0)) / F.col("n"), 6).alias("value"))


def binary_metrics(scored: DataFrame, threshold: float, weight: str | None = None) -> DataFrame:
    """``pairs, accuracy, f1, auc`` of ``label`` (0/1) and ``score``; a row counts ``weight`` times."""
    yes, n = F.col("score") >= threshold, F.col(weight) if weight else F.lit(1)
    tied = scored.groupBy("score").agg(F.sum(n * F.col("label")).alias("pos"), F.sum(n * (1 - F.col("label"))).alias("neg"))
    w = Window.orderBy("score").rowsBetween(Window.unboundedPreceding, -1)
    area = tied.withColumn("below", F.coalesce(F.sum("neg").over(w), F.lit(0))).agg((F.sum(F.col("pos") * (F.col("below") + F.col("neg") / 2)) / F.nullif(F.sum("pos").cast("double") * F.sum("neg"), F.lit(0.0))).alias("auc"))
    many = lambda c: F.sum(F.when(c, n).otherwise(0))
    tp, fp, fn = many(yes & (F.col("label") == 1)), many(yes & (F.col("label") == 0)), many(~yes & (F.col("label") == 1))
    m = scored.agg(F.coalesce(F.sum(n), F.lit(0)).alias("pairs"), F.round(many(yes.cast("int") == F.col("label")) / F.sum(n), 6).alias("accuracy"), F.round(2 * tp / F.nullif(2 * tp + fp + fn, F.lit(0)), 6).alias("f1"))
    return m.join(F.broadcast(area)).select("pairs", "accuracy", "f1", F.round("auc", 6).alias("auc"))


def pairwise_winrate(judgments: DataFrame) -> DataFrame:
    """``a, b, wins, share`` of supplied verdicts; ties count half."""
    won = F.when(F.col("winner") == F.col("a"), 1.0).when(F.col("winner") == F.col("b"), 0.0).otherwise(0.5)
    return judgments.groupBy("a", "b").agg(F.sum(won).alias("wins"), F.round(F.avg(won), 6).alias("share"))


def latency_summary(runs: DataFrame, *by: str) -> DataFrame:
    """``runs, failed, p50, p95`` of ``ms`` by method (failed runs do not count in times)."""
    ok = F.when(F.col("status") == "ok", F.col("ms"))
    return runs.groupBy(*by).agg(F.count("*").alias("runs"), F.count_if(F.col("status") != "ok").alias("failed"), F.round(F.percentile(ok, 0.5), 6).alias("p50"), F.round(F.percentile(ok, 0.95), 6).alias("p95"))


def short_answer_share(matches: DataFrame, queries: DataFrame, n: int = 20) -> DataFrame:
    """``queries, short, share``: queries with fewer than ``n`` patterns."""
    per = queries.select("query_id").join(matches.groupBy("query_id").agg(F.count("*").alias("c")), "query_id", "left")
    return per.agg(F.count("*").alias("queries"), F.count_if(F.coalesce("c", F.lit(0)) < n).alias("short")).withColumn("share", F.round(F.col("short") / F.col("queries"), 6))
