"""The experiment workloads on the given tables, one function a registered query.

What an index would hold (tokens, vocabulary, windows, suffixes) is built once for
a path and kept in the shared folder; queries then read it.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ngramlake.baselines import fm, ranking, scans, suffix
from ngramlake.functions.text import SEP, html_text, key_of, tokens
from ngramlake.operators import analysis, contamination, pairs, retrieval, segments, soft, vectors, vocab, walk
from ngramlake.operators import index as idx
from ngramlake.operators import lookup as lk
from ngramlake.sources.tables import corpus, once, spool, spread, table

THETA, FLOOR, QUERY, WANTED = 0.6, 0.45, 5, 20
SWEEP, BASES = (0.45, 0.5, 0.55, 0.6, 0.7, 0.8), (10, 100, 10000, 1000000)
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}


def query(f):
    QUERIES[f.__name__] = f
    return f


# -------------------------------------------------------------- what is built once
def docs_of(spark: SparkSession, sf: str) -> DataFrame:
    return once(spark, (sf, "corpus"), lambda: spool(corpus(spread(table(spark, sf, "documents")), keep=("lang", "source")), "corpus"))


def vocab_of(spark: SparkSession, sf: str) -> DataFrame:
    return once(spark, (sf, "vocab"), lambda: spool(vocab.build_vocab(docs_of(spark, sf)), "vocab"))


def index_of(spark: SparkSession, sf: str) -> idx.WindowIndex:
    return once(spark, (sf, "index"), lambda: idx.build_index(docs_of(spark, sf), with_postings=False))


def segments_of(spark: SparkSession, sf: str) -> segments.SegmentIndex:
    return once(spark, (sf, "segments"), lambda: segments.build_segments(docs_of(spark, sf)))


def grams_of(spark: SparkSession, sf: str, n: int) -> DataFrame:
    return once(spark, (sf, "grams", n), lambda: spool(vocab.ngram_counts(docs_of(spark, sf), n), "grams"))


def suffixes_of(spark: SparkSession, sf: str) -> DataFrame:
    return once(spark, (sf, "sa"), lambda: spool(suffix.build_suffix_array(docs_of(spark, sf), 8), "sa"))


def items_of(spark: SparkSession, sf: str) -> DataFrame:
    return corpus(table(spark, sf, "benchmark"), "item_id").withColumnRenamed("doc_id", "item_id")


def asked(spark: SparkSession, sf: str, m: int = QUERY) -> DataFrame:
    """Queries: the first ``m`` tokens of every test item."""
    return once(spark, (sf, "asked", m), lambda: spool(soft.queries_of(items_of(spark, sf), "item_id", m=m), "asked"))


def near_of(spark: SparkSession, sf: str, m: int = QUERY, theta: float = FLOOR) -> DataFrame:
    def build():
        q = asked(spark, sf, m).select(F.explode("tokens").alias("token"))
        return spool(vectors.neighbors(q, vocab_of(spark, sf), table(spark, sf, "embeddings"), theta), "near")

    return once(spark, (sf, "near", m, theta), build)


def finder_of(spark: SparkSession, sf: str) -> soft.Finder:
    return soft.segment_finder(segments_of(spark, sf))


def shown(key, sep: str = " "):
    return F.replace(key, F.lit(SEP), F.lit(sep))


def heads(spark: SparkSession, sf: str, longest: int) -> DataFrame:
    """Patterns: the first 1 .. ``longest`` tokens of every item."""
    rows = items_of(spark, sf).where(F.size("tokens") > 0).select(F.explode(F.sequence(F.lit(1), F.least(F.size("tokens"), F.lit(longest)))).alias("n"), "tokens")
    return rows.select("n", key_of(F.slice("tokens", F.lit(1), F.col("n"))).alias("key")).distinct()


# ------------------------------------------------------------------- index queries
@query
def vocab_top(spark, sf):
    v = vocab_of(spark, sf).where("token_id < 100")
    return v.select("token_id", "token", "freq", F.round("p", 9).alias("p"))


@query
def token_stats_by_lang(spark, sf):
    rows = docs_of(spark, sf).select("lang", "doc_id", F.explode_outer("tokens").alias("token"))
    return rows.groupBy("lang").agg(F.countDistinct("doc_id").alias("docs"), F.count("token").alias("tokens"), F.countDistinct("token").alias("types"))


@query
def windows_count(spark, sf):
    r = index_of(spark, sf).runs
    return r.agg(F.sum("run").alias("windows"), F.count("*").alias("distinct_windows"))


@query
def swa_fences(spark, sf):
    return index_of(spark, sf).fences.select("block", shown(F.col("first_key")).alias("first_key"), "entries", "n", "before")


@query
def swa_runs(spark, sf):
    return index_of(spark, sf).runs.groupBy("run").agg(F.count("*").alias("windows"))


@query
def swa_prefix_bytes(spark, sf):
    """Sizes of the keys plain and with shared prefixes cut, by block."""
    coded = idx.prefix_code(index_of(spark, sf).runs)
    plain = index_of(spark, sf).runs.groupBy("block").agg(F.sum(F.length("key")).alias("plain"))
    return coded.groupBy("block").agg(F.sum(F.length("rest")).alias("coded")).join(plain, "block").select("block", "plain", "coded")


@query
def index_sizes(spark, sf):
    """Bytes of the index by compression: none, equal windows counted, and front-coded as stored;
    bytes of the raw text beside."""
    raw = table(spark, sf, "documents").agg(F.sum(F.octet_length("text").cast("long")).alias("text"))
    return idx.key_sizes(index_of(spark, sf)).join(F.broadcast(raw))


@query
def exact_hits(spark, sf):
    p = heads(spark, sf, idx.WINDOW)
    return segments.all_hits(p, segments_of(spark, sf)).select(shown(F.col("key")).alias("pattern"), "hits")


@query
def exact_hits_sql(spark, sf):
    p = heads(spark, sf, idx.WINDOW)
    return lk.exact_lookup_sql(p, index_of(spark, sf)).select(shown(F.col("key")).alias("pattern"), "hits")


@query
def exact_exists(spark, sf):
    p = heads(spark, sf, idx.WINDOW)
    found = segments.all_hits(p, segments_of(spark, sf)).select("key", (F.col("hits") > 0).alias("found"))
    return p.join(found, "key").groupBy("n").agg(F.count("*").alias("patterns"), F.count_if("found").alias("found"))


@query
def exact_occurrences(spark, sf):
    p = asked(spark, sf).select(key_of(F.col("tokens")).alias("key"))
    return segments.occurrences(p, segments_of(spark, sf)).select(shown(F.col("key")).alias("pattern"), "doc_id", "pos")


@query
def exact_long(spark, sf):
    """Patterns longer than a window: the first 15 tokens of every item."""
    p = asked(spark, sf, 15).select(key_of(F.col("tokens")).alias("key"))
    return segments.all_hits(p, segments_of(spark, sf)).select(shown(F.col("key")).alias("pattern"), "hits")


@query
def kgram_table(spark, sf):
    two, three = (vocab.frequent_kgrams(docs_of(spark, sf), 50, k).select(F.lit(k).alias("k"), shown(F.col("key")).alias("gram")) for k in (2, 3))
    return two.unionByName(three)


@query
def ngram_distinct(spark, sf):
    return vocab.ngram_sets(docs_of(spark, sf), 5).groupBy("n").agg(F.count("*").alias("types"))


@query
def sa_lookup(spark, sf):
    text = once(spark, (sf, "sa-text"), lambda: suffix.suffix_texts(suffixes_of(spark, sf), docs_of(spark, sf), 8))
    return suffix.sa_lookup(heads(spark, sf, QUERY), text).select(shown(F.col("key")).alias("pattern"), "hits")


@query
def fm_lookup(spark, sf):
    made = once(spark, (sf, "fm"), lambda: fm.build_fm(suffixes_of(spark, sf), docs_of(spark, sf)))
    return fm.fm_lookup(heads(spark, sf, QUERY), made, QUERY).select(shown(F.col("key")).alias("pattern"), "hits")


@query
def scan_windows(spark, sf):
    return scans.scan_exact(None, heads(spark, sf, QUERY), docs_of(spark, sf), QUERY).select(shown(F.col("key")).alias("pattern"), "hits")


@query
def accesses_per_lookup(spark, sf):
    """Index accesses of a lookup: fenced blocks (one an end) beside binary search probes."""
    text = once(spark, (sf, "sa-text"), lambda: suffix.suffix_texts(suffixes_of(spark, sf), docs_of(spark, sf), 8))
    probes = suffix.sa_lookup(heads(spark, sf, QUERY), text).agg(F.avg("probes").alias("binary_search"))
    p = heads(spark, sf, QUERY).select("key", F.explode(F.array(F.lit(-1), F.lit(1))).alias("sign"))
    blocks = lk.place(p, index_of(spark, sf)).groupBy("key").agg(F.countDistinct("block").alias("b")).agg(F.avg("b").alias("fenced"))
    return probes.join(F.broadcast(blocks)).select(F.round("binary_search", 6).alias("binary_search"), F.round("fenced", 6).alias("fenced"), F.lit(1.0).alias("existence"))


# ------------------------------------------------------------------ vector queries
@query
def neighbors(spark, sf):
    return near_of(spark, sf).select("tok", "nb", "cos")


@query
def surprisal_norm(spark, sf):
    v = vectors.norms(vocab_of(spark, sf))
    return v.select("token", F.round("v", 6).alias("v"))


@query
def whitened_norm(spark, sf):
    lex = vectors.lexicon(vocab_of(spark, sf), table(spark, sf, "embeddings"), ("freq",))
    return vectors.whitened_norms(lex, vocab_of(spark, sf)).select("token", F.round("v", 4).alias("v"))


@query
def penalty_constant(spark, sf):
    v = vectors.norms(vocab_of(spark, sf))
    k = vectors.calibrate_penalty(v)
    return spark.createDataFrame([(round(k, 6), round(2.718281828459045 ** (-k * 5 / (5 * k)), 6))], "kappa double, factor double")


# -------------------------------------------------------------------- soft queries
def _soft(spark, sf, m=QUERY, theta=THETA, **how):
    return soft.soft_search(asked(spark, sf, m), theta, near_of(spark, sf, m).where(F.col("cos") >= theta), finder_of(spark, sf), m, **how)


def _shown(found: DataFrame) -> DataFrame:
    return found.select("query_id", shown(F.col("key")).alias("pattern"), "similarity", "hits")


def edits_of(spark, sf, kind, most=1):
    v = vectors.norms(vocab_of(spark, sf))
    return once(spark, (sf, "edits", kind, most), lambda: soft.Edits(v, vectors.calibrate_penalty(v), kind, most))


@query
def soft_sub(spark, sf):
    return _shown(_soft(spark, sf))


@query
def soft_sub_hardmin(spark, sf):
    return _shown(_soft(spark, sf, hard=True))


@query
def soft_sub_last_bits(spark, sf):
    return _shown(_soft(spark, sf, prune=soft.Prune(last_bits=True), index=index_of(spark, sf)))


@query
def soft_sub_kgram(spark, sf):
    c = docs_of(spark, sf)
    top = once(spark, (sf, "top"), lambda: spool(vocab_of(spark, sf).where("token_id < 100").select("token"), "top"))
    tables = once(spark, (sf, "kgrams"), lambda: [spool(vocab.frequent_kgrams(c, 100, k), "kgrams") for k in (2, 3)])
    return _shown(_soft(spark, sf, prune=soft.Prune(kgram=True), kgrams=(top, tables)))


@query
def soft_ins1(spark, sf):
    return _shown(_soft(spark, sf, edits=edits_of(spark, sf, "ins")))


@query
def soft_del1(spark, sf):
    return _shown(_soft(spark, sf, edits=edits_of(spark, sf, "del")))


@query
def soft_both(spark, sf):
    return _shown(_soft(spark, sf, edits=edits_of(spark, sf, "both", 2)))


@query
def naive_soft(spark, sf):
    q, near = asked(spark, sf, 2), near_of(spark, sf, 2).where(F.col("cos") >= THETA)
    return _shown(soft.naive_search(q, THETA, near, finder_of(spark, sf), 2))


def _floor(spark, sf, m=3):
    return once(spark, (sf, "floor", m), lambda: spool(_soft(spark, sf, m, FLOOR), "floor"))


@query
def soft_topn(spark, sf):
    return soft.top_patterns(_floor(spark, sf), WANTED).select("query_id", "rank", shown(F.col("key")).alias("pattern"), "similarity", "hits")


@query
def adaptive_topn(spark, sf):
    near, find = near_of(spark, sf, 3), finder_of(spark, sf)
    search = lambda q, t: soft.soft_search(q, t, near.where(F.col("cos") >= t), find, 3)
    best = soft.adaptive_search(asked(spark, sf, 3), search, WANTED)
    return best.select("query_id", "rank", shown(F.col("key")).alias("pattern"), "similarity", "hits")


@query
def short_answers(spark, sf):
    return analysis.short_answer_share(_floor(spark, sf), asked(spark, sf, 3), WANTED)


@query
def predecessor_soft(spark, sf):
    q, near = asked(spark, sf, 3), near_of(spark, sf, 3).where(F.col("cos") >= THETA)
    found = ranking.inverted_soft_search(q, docs_of(spark, sf), near, THETA)
    return _shown(found)


@query
def method_ticks(spark, sf):
    """Top patterns with marks: found by the predecessor, found by exact lookup."""
    top = soft.top_patterns(_soft(spark, sf, 3), WANTED)
    old = ranking.inverted_soft_search(asked(spark, sf, 3), docs_of(spark, sf), near_of(spark, sf, 3).where(F.col("cos") >= THETA), THETA).select("query_id", "key").withColumn("in_predecessor", F.lit(True))
    rows = top.join(old, ["query_id", "key"], "left")
    return rows.select("query_id", "rank", shown(F.col("key")).alias("pattern"), "similarity", "hits", F.coalesce("in_predecessor", F.lit(False)).alias("in_predecessor"), (F.col("similarity") == 1).alias("in_exact"))


# ------------------------------------------------------------------ cost measures
def _steps(spark, sf):
    def build():
        trace: list = []
        _soft(spark, sf, trace=trace)
        return spool(analysis.trace_counts(trace), "steps")

    return once(spark, (sf, "steps"), build)


@query
def lookups_count(spark, sf):
    return _steps(spark, sf).groupBy("step").agg(F.sum("candidates").alias("candidates"), F.sum("kept").alias("kept"))


@query
def lookups_geomean(spark, sf):
    t = analysis.lookup_totals(_steps(spark, sf))
    return t.agg(F.round(analysis.geometric_mean(F.col("lookups")), 6).alias("geo_mean"), F.max("lookups").alias("most"), F.sum("lookups").alias("total"))


@query
def growth_bound(spark, sf):
    return analysis.growth_bound(_steps(spark, sf), asked(spark, sf), QUERY)


@query
def ablation_growth(spark, sf):
    """Factor by which lookups grow a query token, with and without iterative pruning."""
    near = near_of(spark, sf).where(F.col("cos") >= THETA)
    return analysis.growth_per_token(analysis.lookups_by_length(_steps(spark, sf), near, asked(spark, sf), QUERY), "pruning")


@query
def threshold_sweep(spark, sf):
    """Patterns and queries with at least N of them, for thresholds from the floor up."""
    found, out = _floor(spark, sf), None
    for t in SWEEP:
        per = asked(spark, sf, 3).select("query_id").join(found.where(F.col("similarity") >= t).groupBy("query_id").agg(F.count("*").alias("c")), "query_id", "left")
        part = per.agg(F.lit(t).alias("theta"), F.coalesce(F.sum("c"), F.lit(0)).alias("patterns"), *[F.count_if(F.coalesce("c", F.lit(0)) >= n).alias(f"n{n}") for n in (1, 5, 20)])
        out = part if out is None else out.unionByName(part)
    return out


@query
def base_sweep(spark, sf):
    """Patterns found and their mean similarity, as the base of the smooth minimum changes."""
    out = None
    for b in BASES:
        part = _soft(spark, sf, 3, base=float(b)).agg(F.lit(b).alias("base"), F.count("*").alias("patterns"), F.round(F.avg("similarity"), 5).alias("mean"))
        out = part if out is None else out.unionByName(part)
    return out


@query
def judge_winrate(spark, sf):
    """Verdicts of a rule (more patterns found wins) between soft search and its predecessor."""
    new = _soft(spark, sf, 3).groupBy("query_id").agg(F.count("*").alias("x"))
    old = ranking.inverted_soft_search(asked(spark, sf, 3), docs_of(spark, sf), near_of(spark, sf, 3).where(F.col("cos") >= THETA), THETA).groupBy("query_id").agg(F.count("*").alias("y"))
    both = asked(spark, sf, 3).select("query_id").join(new, "query_id", "left").join(old, "query_id", "left").fillna(0)
    a, b = F.lit("soft"), F.lit("predecessor")
    verdict = both.select(a.alias("a"), b.alias("b"), F.when(F.col("x") > F.col("y"), a).when(F.col("x") < F.col("y"), b).alias("winner"))
    return analysis.pairwise_winrate(verdict)


@query
def sampling_model(spark, sf):
    totals = walk.ngram_totals(segments_of(spark, sf), vocab_of(spark, sf), QUERY)
    kept = _steps(spark, sf).groupBy("step").agg((F.sum("kept") / asked(spark, sf).count()).alias("kept"))
    near = near_of(spark, sf).where(F.col("cos") >= THETA)
    rows = analysis.sampling_model(near, asked(spark, sf), totals, vocab_of(spark, sf).count(), kept)
    return rows.select("step", F.round("expected", 6).alias("expected"), F.round("kept", 6).alias("kept"))


@query
def zipf_fit(spark, sf):
    return analysis.zipf_fit(vocab_of(spark, sf).select("token", "freq"))


@query
def heaps_fit(spark, sf):
    size = 20
    n = docs_of(spark, sf).select(F.ntile(size).over(Window.orderBy("doc_id")).alias("step"), "doc_id")  # ids only
    rows = docs_of(spark, sf).join(n, "doc_id").select("step", F.explode("tokens").alias("token"))
    return analysis.heaps_fit(analysis.heaps_points(rows))


def runs_of(spark, sf):
    e = table(spark, sf, "events")
    return e.select(F.col("event_type").alias("method"), F.col("value").alias("ms"), F.when(F.col("event_type") == "error", "failed").otherwise("ok").alias("status"))


@query
def latency_p95(spark, sf):
    return analysis.latency_summary(runs_of(spark, sf), "method")


# ------------------------------------------------------------------- contamination
@query
def contam_exact(spark, sf):
    w = contamination.item_windows(items_of(spark, sf))
    return contamination.coverage(w, contamination.exact_matches(w, finder_of(spark, sf)))


@query
def contam_characters(spark, sf):
    """Coverage of every item by exact windows of 50 characters."""
    return contamination.character_coverage(table(spark, sf, "benchmark").select("item_id", "text"), spread(table(spark, sf, "documents")).select("doc_id", "text"))


def planted_items(spark, sf):
    """Every item with its 15th token replaced by the nearest other word, where one is near;
    items without a 15th token stay as they are."""
    def build():
        items = items_of(spark, sf)
        tok = items.select(F.get("tokens", F.lit(14)).alias("token")).where("token is not null").distinct()
        near = vectors.neighbors(tok, vocab_of(spark, sf), table(spark, sf, "embeddings"), THETA).where(F.col("tok") != F.col("nb"))
        best = near.groupBy("tok").agg(F.min(F.struct((-F.col("cos")).alias("c"), "nb")).alias("b")).select("tok", F.col("b.nb").alias("nb"))
        rows = items.join(best, F.get("tokens", F.lit(14)) == F.col("tok"), "left")
        swapped = F.transform("tokens", lambda x, i: F.when((i == 14) & F.col("nb").isNotNull(), F.col("nb")).otherwise(x))
        return spool(rows.select("item_id", swapped.alias("tokens")), "planted")

    return once(spark, (sf, "planted"), build)


def _soft_arm(spark, sf, items):
    w = contamination.item_windows(items)
    exact = spool(contamination.exact_matches(w, finder_of(spark, sf)), "exact")
    search = lambda q: walk.matched(q, contamination.SIMILAR, table(spark, sf, "embeddings"), segments_of(spark, sf))
    matched = spool(contamination.soft_matches(w, exact, search), "matched")
    return contamination.coverage(w, exact), contamination.coverage(w, matched)


def _arms(spark, sf):
    return once(spark, (sf, "arms"), lambda: tuple(spool(x, "arm") for x in _soft_arm(spark, sf, planted_items(spark, sf))))


@query
def contam_soft(spark, sf):
    return _arms(spark, sf)[1]


@query
def contam_extra(spark, sf):
    exact, found = _arms(spark, sf)
    return contamination.gain(found, exact).select("item_id", "windows", "eta")


@query
def contam_report(spark, sf):
    exact, found = _arms(spark, sf)
    whole = scans.scan_contains(table(spark, sf, "documents"), table(spark, sf, "benchmark").select("item_id", F.col("text").alias("pattern"))).select("item_id").distinct().withColumn("truth", F.lit(True))
    flags = found.select("item_id", F.col("dirty").alias("soft")).join(exact.select("item_id", F.col("dirty").alias("exact")), "item_id").join(whole, "item_id", "left").withColumn("truth", F.coalesce("truth", F.lit(False)))
    return contamination.report(flags)


@query
def template_leak(spark, sf):
    """Items with one number against a corpus that holds them with another."""
    def build():
        items = items_of(spark, sf).where(F.size("tokens") >= 20)
        put = lambda n: F.concat(F.slice("tokens", 1, 10), F.array(F.lit(n)), F.expr("slice(tokens, 11, size(tokens))"))
        held = items.select(F.col("item_id").alias("doc_id"), put("17").alias("tokens"))
        own = idx.build_index(held, with_postings=False)
        w = contamination.item_windows(items.select("item_id", put("42").alias("tokens")))
        find = soft.fence_finder(own)
        exact = spool(contamination.exact_matches(w, find), "exact")
        near = vectors.neighbors(w.select(F.explode(F.split("key", SEP)).alias("token")), held.select(F.explode("tokens").alias("token")).distinct(), table(spark, sf, "embeddings"), contamination.SIMILAR)
        rest = w.select("key").distinct().join(exact, "key", "left_anti")
        t = F.split("key", SEP)
        found = soft.soft_search(rest.select(F.col("key").alias("query_id"), t.alias("tokens"), F.size(t).alias("m")), contamination.SIMILAR, spool(near, "near"), find, contamination.SPAN)
        return spool(w.join(found.select(F.col("query_id").alias("key"), F.col("key").alias("match"), "similarity"), "key"), "template")

    rows = once(spark, (sf, "template"), build)
    kinds = contamination.classify(rows.select("item_id", F.split("key", SEP).alias("q"), F.split("match", SEP).alias("p"), "similarity"))
    return kinds.groupBy("item_id", "class").agg(F.count("*").alias("matches"), F.min("similarity").alias("least"))


# ------------------------------------------------------- baselines and applications
@query
def scan_contains(spark, sf):
    return scans.scan_contains(table(spark, sf, "documents"), table(spark, sf, "benchmark").select("item_id", F.col("text").alias("pattern")))


@query
def scan_regex(spark, sf):
    return scans.scan_regex(table(spark, sf, "documents"), r"[a-zA-Z0-9._]+@[a-zA-Z0-9.]+")


@query
def scan_lev(spark, sf):
    names = table(spark, sf, "part").select("p_name").distinct()
    near = scans.scan_levenshtein(names, names.withColumnRenamed("p_name", "other"), "p_name", "other", 3)
    return near.where("p_name < other").select("p_name", "other", "distance")


@query
def scan_k_errors(spark, sf):
    """Least edit distance of each item's whole text to any place of each document."""
    q = table(spark, sf, "benchmark").select("item_id", F.col("text").alias("pattern"))
    return scans.scan_k_errors(table(spark, sf, "documents"), q)


@query
def bm25(spark, sf):
    return ranking.bm25_search(asked(spark, sf), docs_of(spark, sf), 10)


@query
def tfidf(spark, sf):
    return ranking.tfidf_search(asked(spark, sf), docs_of(spark, sf), 10)


@query
def dense_topk(spark, sf):
    v = table(spark, sf, "embeddings")
    return ranking.dense_search(v, v.where("vec_id % 100 = 0"), 10)


@query
def dense_cells(spark, sf):
    v = table(spark, sf, "embeddings")
    return ranking.dense_search_cells(v, v.where("vec_id % 100 = 0"), 10)


def truth_of(spark, sf):
    held = once(spark, (sf, "held"), lambda: spool(scan_contains(spark, sf), "held"))
    return held.select(F.col("item_id").alias("query_id"), "doc_id")


def ranked_of(spark, sf):
    return once(spark, (sf, "ranked"), lambda: spool(ranking.bm25_search(asked(spark, sf, 10), docs_of(spark, sf), 1000), "ranked"))


@query
def ir_p_at_k(spark, sf):
    q = truth_of(spark, sf).select("query_id").distinct()
    one, many = (analysis.precision_at(ranked_of(spark, sf), truth_of(spark, sf), k, q).withColumnRenamed("value", f"p{k}") for k in (1, 20))
    return one.join(many, "query_id")


@query
def ir_r_at_k(spark, sf):
    few, many = (analysis.recall_at(ranked_of(spark, sf), truth_of(spark, sf), k).withColumnRenamed("value", f"r{k}") for k in (5, 1000))
    return few.join(many, "query_id")


@query
def ir_soft(spark, sf):
    """The same retrieval by soft matches of five-token windows."""
    g = retrieval.query_grams(asked(spark, sf, 10), QUERY)
    q = spool(g.select("query_id", "tokens", "m").distinct(), "gram-queries")
    near = vectors.neighbors(q.select(F.explode("tokens").alias("token")), vocab_of(spark, sf), table(spark, sf, "embeddings"), THETA)
    found = spool(soft.soft_search(q, THETA, spool(near, "near"), finder_of(spark, sf), QUERY), "gram-matches")
    best = retrieval.soft_retrieve(g, found, segments_of(spark, sf), docs_of(spark, sf).count())
    truth = truth_of(spark, sf)
    few = analysis.recall_at(best, truth, 5).withColumnRenamed("value", "r5")
    return few.join(analysis.precision_at(best, truth, 1, truth.select("query_id").distinct()).withColumnRenamed("value", "p1"), "query_id")


def pair_blocks_of(spark, sf):
    return once(spark, (sf, "pair-blocks"), lambda: pairs.pair_blocks(corpus(spread(table(spark, sf, "documents"))), QUERY))


def _label():
    return (F.col("jaccard") >= 0.5).cast("int").alias("label")


@query
def paraphrase(spark, sf):
    return pairs.shared_pairs(pair_blocks_of(spark, sf), documents=True).select("a", "b", "jaccard", "score", _label())


@query
def paraphrase_metrics(spark, sf):
    """Over all pairs of documents, counted by classes of equal texts."""
    scored = pairs.shared_pairs(pair_blocks_of(spark, sf)).select("score", _label(), "n")
    tied = once(spark, (sf, "pair-scores"), lambda: spool(scored.groupBy("score", "label").agg(F.sum("n").alias("n")), "pair-scores"))
    return analysis.binary_metrics(tied, 0.6, "n")


@query
def pages_text(spark, sf):
    p = table(spark, sf, "pages").select("page_id", html_text(F.col("html")).alias("text"))
    return p.select("page_id", F.length("text").alias("chars"), F.size(tokens(F.col("text"))).alias("tokens"))


@query
def conv_queries(spark, sf):
    c = table(spark, sf, "conversations").where("role = 'user'").select("conv_id", "turn", tokens(F.col("text")).alias("t"))
    return c.where(F.size("t") > 0).select("conv_id", "turn", F.array_join(F.slice("t", 1, 10), " ").alias("query"), F.least(F.size("t"), F.lit(10)).alias("m"))


@query
def tokenizer_modes(spark, sf):
    d = table(spark, sf, "documents")
    modes = ("word", "word_cased", "whitespace", "char", "piece")
    return d.agg(*[F.sum(F.size(tokens(F.col("text"), m))).alias(m) for m in modes])
