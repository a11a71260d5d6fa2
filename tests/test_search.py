"""Soft search and lookup against brute force on small corpora."""

import itertools

import pytest
from pyspark.sql import functions as F

from ngramlake.baselines import fm, ranking, scans, suffix
from ngramlake.functions import similarity as sim
from ngramlake.functions.text import SEP
from ngramlake.operators import index as idx
from ngramlake.operators import lookup, soft, vocab

LINES = ["the red cat sat on the mat", "a red dog sat on a mat", "the cat sat", "red cats sat on mats , the end", "", None, "dog", "the red , cat sat on the mat"]
NEAR = {("cat", "cats"): 0.8, ("cats", "cat"): 0.8, ("dog", "cat"): 0.7, ("cat", "dog"): 0.7, ("mat", "mats"): 0.9, ("mats", "mat"): 0.9, ("the", "a"): 0.6, ("a", "the"): 0.6}


@pytest.fixture(scope="module")
def world(spark):
    from ngramlake.sources.tables import corpus

    docs = corpus(spark.createDataFrame(list(enumerate(LINES)), "doc_id long, text string"))
    words = sorted({w for line in LINES if line for w in line.split()})
    near = spark.createDataFrame([(a, b, c) for (a, b), c in NEAR.items()] + [(w, w, 1.0) for w in words], "tok string, nb string, cos double")
    norms = spark.createDataFrame([(w, 0.4 if w in ("the", ",", "a") else 3.0) for w in words], "token string, v double")
    return docs, near, norms, idx.build_index(docs, 6, 4), words


def brute(q, theta, kinds, norm, kappa=1.0, hits=False):
    cos = lambda a, b: 1.0 if a == b else NEAR.get((a, b), -9.0)
    texts = [line.split() for line in LINES if line]
    grams = {tuple(t[i : i + n]) for t in texts for n in range(1, 7) for i in range(len(t) - n + 1)}
    out = {}
    for g in grams:
        s = round(sim.align(list(q), list(g), lambda a, b: max(cos(a, b), -1), norm, kappa, edits=kinds)[0], 6)
        # tokens that are no neighbours at the threshold are no substitutions
        if s >= theta:
            out[SEP.join(g)] = s
    return out


def found(df):
    return {r["key"]: r["similarity"] for r in df.collect()}


def test_worked_index(spark):
    from ngramlake.sources.tables import corpus

    docs = corpus(spark.createDataFrame([(0, "pattern match for a trillion scale corpus")], "doc_id long, text string"))
    index = idx.build_index(docs, 2, 3)
    rows = [r["key"].replace(SEP, " ") for r in index.runs.orderBy("rank").collect()]
    assert rows == ["a trillion", "corpus", "for a", "match for", "pattern match", "scale corpus", "trillion scale"]
    assert rows.index("pattern match") == 4
    assert [r["first_key"].split(SEP)[0] for r in index.fences.orderBy("block").collect()] == ["a", "match", "trillion"]
    assert idx.choose_block(10**6, 48, 10**6) == 64


def test_lookups_agree(spark, world):
    docs, _, _, index, _ = world
    texts = [line.split() for line in LINES if line]
    every = {tuple(t[i : i + n]) for t in texts for n in range(1, 6) for i in range(len(t) - n + 1)} | {("cat", "red"), ("zebra",), ("the", "zebra")}
    p = spark.createDataFrame([(SEP.join(g),) for g in every], "key string")
    want = {SEP.join(g): sum(t[i : i + len(g)] == list(g) for t in texts for i in range(len(t))) for g in every}
    rows = lambda df: {r["key"]: r["hits"] for r in df.collect()}
    assert rows(lookup.exact_lookup(p, index)) == want
    assert rows(lookup.exact_lookup(p, index, memory=0)) == want
    for memory in (lookup.FENCE_BYTES, 0):
        assert {r["key"] for r in lookup.exists(p, index, memory).collect()} == {k for k, v in want.items() if v}
    assert rows(lookup.exact_lookup_sql(p, index)) == want
    assert rows(scans.scan_exact(None, p, docs, 5)) == want
    sa = suffix.build_suffix_array(docs, 8)
    assert rows(suffix.sa_lookup(p, suffix.suffix_texts(sa, docs, 8))) == want
    assert rows(fm.fm_lookup(p, fm.build_fm(sa, docs), 5)) == want
    places = lookup.occurrences(p, index).groupBy("key").count().collect()
    assert {r["key"]: r["count"] for r in places} == {k: v for k, v in want.items() if v}
    long = spark.createDataFrame([(SEP.join("the red cat sat on the mat".split()),), (SEP.join("the red cat sat on the end".split()),)], "key string")
    assert sorted(rows(lookup.long_lookup(long, index, docs)).values()) == [0, 1]
    for look in (lookup.exact_lookup, lookup.exists):  # refused, not answered by 0
        with pytest.raises(Exception, match="longer than the index"):
            look(long, index).collect()


@pytest.mark.parametrize("kind", ["none", "ins", "del", "both"])
def test_soft_search_is_exhaustive(spark, world, kind):
    docs, near, norms, index, words = world
    theta, kappa = 0.55, 1.0
    q = spark.createDataFrame([(1, ["the", "red", "cat"], 3)], "query_id long, tokens array<string>, m int")
    edits = None if kind == "none" else soft.Edits(norms, kappa, kind, 3)
    got = found(soft.soft_search(q, theta, near.where(F.col("cos") >= theta), soft.fence_finder(index), 3, edits=edits, max_len=6))
    norm = lambda t: 0.4 if t in ("the", ",", "a") else 3.0
    assert got == brute(["the", "red", "cat"], theta, kind, norm, kappa)


def test_prunings_and_methods_agree(spark, world):
    docs, near, _, index, _ = world
    theta = 0.55
    q = spark.createDataFrame([(1, ["the", "cat", "sat"], 3), (2, ["red", "dog"], 2), (3, ["zebra"], 1)], "query_id long, tokens array<string>, m int")
    n = near.where(F.col("cos") >= theta)
    find = soft.fence_finder(index)
    rows = lambda df: {(r["query_id"], r["key"]): (r["similarity"], r["hits"]) for r in df.collect()}
    base = rows(soft.soft_search(q, theta, n, find, 3))
    assert base
    top = vocab.token_counts(docs).orderBy(F.desc("freq"), "token").limit(4).select("token")
    tables = [vocab.frequent_kgrams(docs, 4, k) for k in (2, 3)]
    for it, kg, lb in itertools.product((True, False), repeat=3):
        p = soft.Prune(it, kg, lb, 2)
        assert rows(soft.soft_search(q, theta, n, find, 3, prune=p, kgrams=(top, tables), index=index)) == base
    assert rows(soft.naive_search(q, theta, n, find, 3)) == base
    grams = vocab.ngram_counts(docs, 1).unionByName(vocab.ngram_counts(docs, 2)).unionByName(vocab.ngram_counts(docs, 3))
    assert rows(soft.soft_search(q, theta, n, soft.gram_finder(grams), 3)) == base
    hard = rows(soft.soft_search(q, theta, n, find, 3, hard=True))
    old = {(r["query_id"], r["key"]): (r["similarity"], r["hits"]) for r in ranking.inverted_soft_search(q, docs, n, theta).collect()}
    assert hard == old
    plan = ranking.inverted_soft_search(q, docs, n, theta)._jdf.queryExecution().toString()
    assert "Join" not in plan and "Generate" not in plan  # postings stay in their tasks
    tight = rows(soft.soft_search(q, 0.75, near.where(F.col("cos") >= 0.75), find, 3))
    assert set(tight) <= set(base)


def test_adaptive_equals_floor(spark, world):
    _, near, _, index, _ = world
    q = spark.createDataFrame([(1, ["the", "cat"], 2), (2, ["dog"], 1)], "query_id long, tokens array<string>, m int")
    search = lambda x, t: soft.soft_search(x, t, near.where(F.col("cos") >= t), soft.fence_finder(index), 2)
    rows = lambda df: sorted((r["query_id"], r["rank"], r["key"], r["similarity"]) for r in df.collect())
    assert rows(soft.adaptive_search(q, search, 2)) == rows(soft.adaptive_search(q, search, 2, strategy="floor"))


def test_append_and_prefix_code(spark, world):
    from ngramlake.sources.tables import corpus

    docs, _, _, index, _ = world
    more = corpus(spark.createDataFrame([(100, "the red cat sat")], "doc_id long, text string"))
    grown = idx.append_index(index, more)
    fresh = idx.build_index(docs.unionByName(more), 6, 4)
    rows = lambda i: [tuple(r) for r in i.runs.orderBy("rank").select("block", "rank", "key", "run").collect()]
    assert rows(idx.compact_index(grown)) == rows(fresh)
    asked = fresh.runs.select("key")
    count = lambda i: sorted(tuple(r) for r in lookup.exact_lookup(asked, i).collect())
    places = lambda i: sorted(tuple(r) for r in lookup.occurrences(asked, i).collect())
    assert count(grown) == count(fresh) == count(idx.compact_index(grown))
    assert places(grown) == places(fresh) == places(idx.compact_index(grown))
    assert lookup.exists(asked, grown).count() == asked.count()
    coded = {r["rank"]: r for r in idx.prefix_code(fresh.runs).collect()}
    last = ""
    for block, rank, key, _ in rows(fresh):
        last = last if rank and block == coded[rank - 1]["block"] else ""
        assert last[: coded[rank]["shared"]] + coded[rank]["rest"] == key
        last = key


def test_blocks_round_trip():
    keys = sorted({b"a", b"a\x01b", b"a\x01bc", "é\x01x".encode(), b"b" * 70_000, b"b" * 70_001})
    got, runs = idx.decode_block(idx.encode_block(keys, range(len(keys))))
    assert got == keys and runs.tolist() == list(range(len(keys)))
    assert idx.decode_block(idx.encode_block([], []))[0] == []


def test_lookup_reads_asked_shards_only(spark):
    """A step's plan scans the folders of the shards its patterns fall into, and moves patterns."""
    from ngramlake.sources.tables import corpus

    docs = corpus(spark.createDataFrame([(i, f"w{i:04d} x") for i in range(600)], "doc_id long, text string"))
    index = idx.build_index(docs, 2, 1, with_postings=False)
    assert index.blocks.select("shard").distinct().count() > 2
    found = lookup.exists(spark.createDataFrame([("w0003",), ("zebra",), ("w9",)], "key string"), index)
    assert [r[0] for r in found.collect()] == ["w0003"]
    plan = found._jdf.queryExecution().toString()
    scan = next(line for line in plan.splitlines() if "FileScan" in line and "body" in line)
    assert "IN (0,2)" in scan.split("PartitionFilters")[1].split("]")[0] + "]"
    assert "BroadcastExchange" in plan and "runs-" not in plan


def test_control_characters_hold_no_token(spark):
    from ngramlake.functions.text import tokens

    df = spark.createDataFrame([("a\x00b \x01 c\x02\x1fd",)], "t string")
    for mode in ("word", "whitespace", "char", "word_cased"):
        assert df.select(tokens(F.col("t"), mode)).first()[0] == ["a", "b", "c", "d"]


def test_k_error_scan(spark):
    df = spark.createDataFrame([("the quick brown fox", "quikc"), ("abc", "abc"), ("", "ab"), ("xaxbxcx", "abc")], "t string, p string")
    assert [r[0] for r in df.select(scans.k_error_distance("t", "p")).collect()] == [1, 0, 2, 2]


def test_k_errors_of_every_pattern(spark):
    texts = ["the red cat sat", "", None, "a rad cat", "x" * 1100 + "thered cat", "cat é dog"]
    patterns = ["red cat", "", None, "é dog", "t", "the red cat sat on the mat by the door"]

    def brute(p, t):
        row = [0] * (len(t) + 1)
        for i, c in enumerate(p, 1):
            new = [i]
            for j, d in enumerate(t, 1):
                new.append(min(row[j - 1] + (c != d), row[j] + 1, new[-1] + 1))
            row = new
        return min(row)

    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    asked = spark.createDataFrame(list(enumerate(patterns)), "item_id long, pattern string")
    want = {(i, d, brute(p or "", t or "")) for i, p in enumerate(patterns) for d, t in enumerate(texts)}
    for block in (1 << 18, 10):
        assert {tuple(r) for r in scans.scan_k_errors(docs, asked, block=block).collect()} == want


def test_scans_and_contamination_read_every_item(spark, sf):
    from ngramlake.plans import workloads

    items = {r.item_id: r.tokens for r in workloads.items_of(spark, sf).collect()}
    docs = spark.read.parquet(f"{sf}/documents.parquet").count()
    assert workloads.QUERIES["scan_k_errors"](spark, sf).groupBy("item_id").count().where(F.col("count") == docs).count() == len(items)
    planted = {r.item_id: r.tokens for r in workloads.planted_items(spark, sf).collect()}
    assert planted.keys() == items.keys()
    assert all(planted[i] == t for i, t in items.items() if len(t) < 15)


def test_planted_short_items_pass_through(spark, tmp_path):
    import shutil

    from ngramlake.plans import workloads

    for t in ("documents", "embeddings"):
        shutil.copy(f"/root/testdata/sf0.001/{t}.parquet", tmp_path)
    short = ["only four words here", " ".join(["word"] * 16)]
    spark.createDataFrame(list(enumerate(short)), "item_id long, text string").coalesce(1).write.parquet(f"{tmp_path}/benchmark.parquet")
    got = {r.item_id: r.tokens for r in workloads.planted_items(spark, str(tmp_path)).collect()}
    assert got[0] == short[0].split() and len(got[1]) == 16


@pytest.mark.parametrize("size", ["sf0.01", "sf0.1"])
def test_cells_recall(spark, size):
    v = spark.read.parquet(f"/root/testdata/{size}/embeddings.parquet")
    q = v.where("vec_id % 100 = 0")
    want = {(r.query_id, r.vec_id) for r in ranking.dense_search(v, q, 10).collect()}
    got = {(r.query_id, r.vec_id) for r in ranking.dense_search_cells(v, q, 10).collect()}
    assert len(got & want) >= 0.9 * len(want)


def test_pairs_of_crowded_grams(spark):
    from ngramlake.operators import analysis, retrieval

    copies, near = "a b c d e f g h", "a b c d e f x y"
    texts = [copies] * 13 + [near] * 12 + ["z z z z z z"] * 2 + ["no pair is in here at all", "too short", "too short"]
    docs = spark.createDataFrame([(i, t.split()) for i, t in enumerate(texts)], "doc_id long, tokens array<string>")
    grams = {i: {tuple(t.split()[k : k + 5]) for k in range(len(t.split()) - 4)} for i, t in enumerate(texts)}
    want = set()
    for a, b in itertools.combinations(range(len(texts)), 2):
        if c := len(grams[a] & grams[b]):
            want.add((a, b, round(c / len(grams[a] | grams[b]), 6), round((c / len(grams[a]) + c / len(grams[b])) / 2, 6)))
    members = retrieval.text_classes(docs)
    one = docs.join(members.where("doc_id = rep"), "doc_id", "left_semi")
    pairs = retrieval.class_pairs(members, vocab.ngrams(one, 5).select("doc_id", "key").distinct())
    got = retrieval.document_pairs(pairs, members)
    rows = got.collect()
    assert {tuple(r) for r in rows} == want and len(rows) == len(want)
    label = (F.col("jaccard") >= 0.5).cast("int").alias("label")
    assert analysis.binary_metrics(pairs.select("score", label, "n"), 0.6, "n").first() == analysis.binary_metrics(got.select("score", label), 0.6).first()


def test_pairs_are_counted_block_against_block(spark, tmp_path):
    """Every pair of documents as by brute force, over several blocks and with names that meet in 64 bits, and none is shuffled."""
    import random

    import numpy as np

    from ngramlake.operators import pairs
    from ngramlake.plans.workloads import QUERIES

    rnd = random.Random(4)
    common = " ".join(rnd.choices("abcdefgh", k=12))
    texts = [f"{' '.join(rnd.choices('abc', k=rnd.randint(3, 30)))} {common if i % 3 else ''}" for i in range(60)] + ["a b c d e f g h"] * 13 + ["x x x x x x", "y y y y", "", None, "only here is this text of mine"]
    grams = {i: {tuple(w[k : k + 5]) for k in range(len(w) - 4)} for i, w in enumerate((t or "").split() for t in texts)}
    want = set()
    for a, b in itertools.combinations(range(len(texts)), 2):
        if c := len(grams[a] & grams[b]):
            want.add((a, b, round(c / len(grams[a] | grams[b]), 6), round((c / len(grams[a]) + c / len(grams[b])) / 2, 6)))
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    docs = df.selectExpr("doc_id", "filter(split(coalesce(text, ''), ' '), w -> w <> '') as tokens")
    for most in (7, 2048):
        blocks = pairs.pair_blocks(docs.repartition(3), 5, tokens=400, most=most)
        rows = [tuple(r)[:4] for r in pairs.shared_pairs(blocks, documents=True).collect()]
        assert set(rows) == want and len(rows) == len(want)
        assert pairs.shared_pairs(blocks).agg(F.sum("n")).first()[0] == len(want)
    # equal 64 bits of a name: the other 32 decide
    block = pairs.Block.__new__(pairs.Block)
    other = pairs.Block.__new__(pairs.Block)
    block.chunk, block.one, block.two = 0, np.array([3, 5, 5, 5, 9], np.uint64), np.array([1, 1, 2, 4, 1], np.uint32)
    other.chunk, other.one, other.two = 1, np.array([5, 5, 9, 11], np.uint64), np.array([2, 4, 7, 1], np.uint32)
    assert sorted(zip(*(s.tolist() for s in pairs._common(block, other)), strict=True)) == [(2, 0), (3, 1)]
    df.write.parquet(f"{tmp_path}/documents.parquet")
    plan = QUERIES["paraphrase"](spark, str(tmp_path))._jdf.queryExecution().executedPlan().toString()
    assert "hashpartitioning" not in plan and "SortMergeJoin" not in plan and "Sort" not in plan


def test_whitened_norms_join_no_vectors(spark, sf):
    """Vectors go from the lexicon to the sums without a join or a broadcast, with the same norms."""
    from ngramlake.operators import vectors
    from ngramlake.plans import workloads

    plan = workloads.QUERIES["whitened_norm"](spark, sf)._jdf.queryExecution().toString()
    assert "Join" not in plan and "Broadcast" not in plan
    v = workloads.vocab_of(spark, sf).where("freq > 50")
    lex = lambda keep: vectors.lexicon(v, spark.read.parquet(f"{sf}/embeddings.parquet"), keep)
    norm = lambda x: {r.token: round(r.v, 6) for r in vectors.whitened_norms(x, v).collect()}
    assert norm(lex(())) == norm(lex(("freq",))) and "BroadcastHashJoin" not in vectors.whitened_norms(lex(()), v)._jdf.queryExecution().toString()
    assert vectors.whitened_norms(lex(("freq",)).where("false"), v).count() == 0


@pytest.mark.parametrize("most", [1, 7, 1 << 20])
def test_segments_find_every_pattern(spark, world, most):
    """Counts and places of patterns of any length, over segments of one, some and all documents."""
    from ngramlake.operators import segments

    docs = world[0]
    texts = {i: line.split() for i, line in enumerate(LINES) if line}
    every = {tuple(t[i : i + n]) for t in texts.values() for n in range(1, 9) for i in range(len(t) - n + 1)} | {("cat", "red"), ("zebra",), ("the", "red", "cat", "sat", "on", "the", "end")}
    p = spark.createDataFrame([(SEP.join(g),) for g in every] + [("",), ("cat",)], "key string")
    at = {(SEP.join(g), d, i) for g in every for d, t in texts.items() for i in range(len(t)) if t[i : i + len(g)] == list(g)}
    index = segments.build_segments(docs, 3, most)
    assert index.rows.count() >= (6 if most == 1 else 1)
    hits = {SEP.join(g): sum(k == SEP.join(g) for k, _, _ in at) for g in every}
    assert {r["key"]: r["hits"] for r in segments.all_hits(p, index).collect()} == hits
    assert {r["key"]: r["hits"] for r in segments.hits(p, index).collect()} == {k: n for k, n in hits.items() if n}
    assert [tuple(r) for r in sorted(segments.occurrences(p, index).collect())] == sorted(at)
    assert segments.hits(p.where("false"), index).count() == 0
    assert segments.hits(p, segments.build_segments(docs.where("doc_id in (4, 5)"), 3)).count() == 0


@pytest.mark.parametrize("name", ["exact_long", "exact_hits", "exact_exists", "exact_occurrences", "soft_topn", "contam_exact", "growth_bound"])
def test_lookups_build_no_window_index(spark, sf, name):
    """They read segments, smaller than 1.5 times the text; no table of whole windows is written."""
    from ngramlake.plans import workloads
    from ngramlake.sources.tables import table

    own = f"{sf}/."
    assert workloads.QUERIES[name](spark, own).count()
    assert (own, "index") not in spark._ngram_built
    text = table(spark, own, "documents").agg(F.sum(F.octet_length("text").cast("long"))).first()[0]
    assert idx.file_bytes(workloads.segments_of(spark, own).rows) < 1.5 * text


def test_index_of_the_workloads_keeps_no_postings(spark, sf):
    """Places come from the segments; nothing reads postings of the window index."""
    from ngramlake.plans import workloads

    assert workloads.index_of(spark, sf).postings is None


@pytest.mark.parametrize("most", [5, 10**6])
def test_walk_finds_what_soft_search_finds_and_writes_no_candidates(spark, sf, monkeypatch, most):
    import random

    from ngramlake.operators import segments, vectors, walk
    from ngramlake.sources.tables import corpus, table

    rng = random.Random(4)
    words = ["walking", "walked", "walker", "talking", "talked", "1984", "1985", "19", "sea", "seas", "season", "a"]
    docs = corpus(spark.createDataFrame([(i, " ".join(rng.choices(words, k=rng.randint(0, 9)))) for i in range(60)], "doc_id long, text string"))
    asked = [[rng.choice([*words, "walks", "absent"]) for _ in range(rng.randint(1, 4))] for _ in range(40)]
    q = spark.createDataFrame([(" ".join(t), t, len(t)) for t in {tuple(x): x for x in asked}.values()], "query_id string, tokens array<string>, m int")
    index, table = segments.build_segments(docs, 4, 40), table(spark, sf, "embeddings")
    assert index.rows.count() > 3
    vocab = docs.select(F.explode("tokens").alias("token")).distinct()
    near = vectors.neighbors(q.select(F.explode("tokens").alias("token")), vocab, table, 0.3)
    assert near.count() > 30
    want = {r[0] for r in soft.soft_search(q, 0.3, near, soft.segment_finder(index), 4).select("query_id").distinct().collect()}
    monkeypatch.setattr(walk, "TOKENS", most)
    monkeypatch.setattr(walk, "STEP", 7)
    monkeypatch.setattr(soft, "spool", None)  # nothing is written on the way
    monkeypatch.setattr(vectors, "neighbors", None)
    got = [r[0] for r in walk.matched(q, 0.3, table, index).collect()]
    assert sorted(got) == sorted(want) and 5 < len(got) < q.count()


@pytest.mark.parametrize("hard, pairs", [(False, 10**6), (False, 3), (True, 10**6)])
def test_substitutions_grow_in_the_segments(spark, monkeypatch, hard, pairs):
    """Patterns, similarities and hits of the search step by step, and no candidate is written or asked."""
    import random

    from ngramlake.operators import segments, vocab, walk
    from ngramlake.sources.tables import corpus

    rng = random.Random(9)
    words = ["a", "b", "c", "dé", "e", "19", "x"]
    docs = corpus(spark.createDataFrame([(i, " ".join(rng.choices(words, k=rng.choice([0, 1, 2, 9, 30])))) for i in range(60)] + [(99, None)], "doc_id long, text string"))
    near = spark.createDataFrame([(x, y, 1.0 if x == y else round(rng.uniform(0.3, 0.99), 6)) for x in [*words, "gone"] for y in words if x == y or rng.random() < 0.6], "tok string, nb string, cos double")
    asked = [(k // 2, rng.choices([*words, "gone", "never"], k=rng.randint(1, 5))) for k in range(40)] + [(7, ["a", "b"]), (7, ["a", "b"]), (7, ["b", "a"]), (None, ["c"])]
    q = spark.createDataFrame([(i, t, len(t)) for i, t in asked], "query_id long, tokens array<string>, m int")
    grams = vocab.ngram_counts(docs, 1)
    for n in (2, 3, 4):
        grams = grams.unionByName(vocab.ngram_counts(docs, n))
    ask = lambda find: sorted(map(str, soft.soft_search(q, 0.5, near, find, 4, hard=hard).collect()))
    want = ask(soft.gram_finder(grams))
    index = segments.build_segments(docs, 4, 40)
    assert index.rows.count() > 3
    if pairs == 3:
        groups = walk.near_groups(q, near.withColumnRenamed("cos", "a"), pairs)
        assert groups.rdd.getNumPartitions() <= -(-(n := groups.count()) // 2) and n > 3  # no task of nothing for each empty file
    monkeypatch.setattr(walk, "STEP", 5)
    monkeypatch.setattr(walk, "AT_ONCE", 2)
    monkeypatch.setattr(walk.grown, "__defaults__", (*walk.grown.__defaults__[:-1], pairs))
    monkeypatch.setattr(soft, "spool", None)
    monkeypatch.setattr(segments, "_answers", None)
    assert ask(soft.segment_finder(index)) == want and len(want) > 100
    nothing = soft.soft_search(q, 0.5, near.where("false"), soft.segment_finder(index), 4, hard=hard)
    assert nothing.count() == soft.soft_search(q.where("false"), 0.5, near, soft.segment_finder(index), 4).count() == 0


def test_vectors_from_the_sent_table_are_the_same():
    """The walk sends the table in 32 bits; sums are of 64, so cosines round as in ``neighbors``."""
    import numpy as np

    from ngramlake.operators import vectors

    table = np.random.default_rng(2).normal(size=(50, 64)).astype(np.float32)
    words = ["walking", "1984", "a", "seas"] * 3
    one, two = vectors.word_vectors(words, table), vectors.word_vectors(words, table.astype(np.float64))
    assert one.dtype == np.float64 and (one == two).all()


def test_a_walk_keeps_nothing_of_its_segment():
    """Workers live on: neighbours and nodes go with the walk, not with some later collection."""
    import gc
    import weakref

    import numpy as np

    from ngramlake.operators import walk

    counts = []
    levels = walk.tree(iter([np.array([1, 1, 1, 2, 3]), np.array([0, 1, 1, 3, 1])]), counts)
    assert [x.tolist() for x in counts] == [[3, 1, 1], [2, 1, 1]]
    near = (np.array([0, 0, 1]) << 32) | np.array([1, 2, 3])
    group = {"slots": np.array([[0, 1], [0, -1]]), "m": np.array([2, 1])}
    gc.collect()
    gc.disable()
    try:
        got = [(n, q.tolist(), at.tolist()) for n, q, at, _ in walk.walk(group, near, np.zeros(3), levels, 0.5)]
        gone = [weakref.ref(x) for x in (near, levels[0], levels[1])]
        del near, levels
        assert all(x() is None for x in gone)
    finally:
        gc.enable()
    assert sorted(zip(*got[0][1:])) == [(0, 0), (0, 1), (1, 0), (1, 1)] and got[1] == (2, [0], [1])


def test_ngram_totals_send_no_short_ngrams(spark, monkeypatch):
    import random

    from ngramlake.operators import segments, vocab, walk
    from ngramlake.sources.tables import corpus

    rng = random.Random(6)
    rows = [(i, " ".join(rng.choices(["a", "b", "c", "dé"], k=rng.choice([0, 1, 2, 3, 30])))) for i in range(80)]
    docs = corpus(spark.createDataFrame(rows, "doc_id long, text string"))
    index = segments.build_segments(docs, 10, 60)
    assert index.rows.count() > 3
    want = {r["n"]: r["count"] for r in vocab.ngram_sets(docs, 5).groupBy("n").count().collect()}
    got = walk.ngram_totals(index, vocab.build_vocab(docs), 5)
    assert {r["n"]: r["types"] for r in got.collect()} == want
    # what moves: windows packed by segment and bucket, not one row for each n-gram
    sent = index.rows.select("names", "codes", "places").mapInArrow(walk._parts(5, 4), walk.PART)
    assert 0 < sent.count() <= 4 * index.rows.count() < sum(want.values())
