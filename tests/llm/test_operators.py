"""The training-data operators against brute force, with hard rows in every table."""

import collections
import hashlib
import random
import zlib

import numpy as np
import pytest

public_tokenizers = pytest.importorskip("public_tokenizers")
pytest.importorskip("ngramlake.llm.queries")

from pyspark.sql import functions as F  # noqa: E402

from ngramlake.llm import common, language_id, line_dedup, lm_scoring, media, mixing, near_dedup, packing, suffix_dedup, url_filter, vector_search  # noqa: E402

PATH = public_tokenizers.path("word_bpe_49k.json")
KIND = "doc_id long, text string, lang string, source string, n_chars long, score string"


def words(rnd, n, pool="abcdefgh"):
    return " ".join("".join(rnd.choice(pool) for _ in range(rnd.randint(2, 7))) for _ in range(n))


@pytest.fixture(scope="module")
def docs(spark):
    rnd = random.Random(7)
    base = [words(rnd, 60) for _ in range(6)]
    texts = [None, "", "  \n\n ", "42 !!", "one", "two words", "same text here", "same text here", base[0], base[0], base[0] + " tail", base[1] + "\n" + base[2], base[2] + "\n" + base[1], "x" * 30_000, "É été ñandú ß İx b"]
    texts += [base[3] + "\n" + words(rnd, 40) + "\n" + base[4] for _ in range(4)] + [words(rnd, 30) for _ in range(6)]
    rows = [(i, t, ["en", "de", None][i % 3], ["s1", "s2", None][i % 3], 1, "extra") for i, t in enumerate(texts)]
    rows += [(None, "null id text here", "en", "s1", 1, "x"), (8, base[0], "en", "s1", 1, "again")]
    return spark.createDataFrame(rows, KIND)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], KIND)


def test_packing(spark, docs, empty):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(PATH)
    rows = packing.pack_documents(docs, PATH).collect()
    want = collections.Counter((r.doc_id, tuple(t.encode(r.text or "", add_special_tokens=False).ids + [2])) for r in docs.collect())
    pieces = collections.defaultdict(list)
    for r in rows:
        pieces[r.doc_id].append(r)
    ids = {d: x for d, x in want}
    for d, parts in pieces.items():
        full = ids[d]
        for p in parts:
            assert p.doc_tokens == len(full)
            assert p.ids_crc32 == zlib.crc32(np.array(full[p.start : p.start + p.length], "<u4").tobytes())
        assert sum(p.length for p in parts) == sum(n * len(x) for (d2, x), n in want.items() if d2 == d)
    at = collections.defaultdict(int)
    for r in sorted(rows, key=lambda r: (r.sequence_id, r.offset)):
        assert r.offset == at[r.sequence_id]
        at[r.sequence_id] += r.length
    assert max(at.values()) <= packing.CAPACITY
    assert packing.pack_documents(empty, PATH).count() == 0


def test_packing_wastes_little():
    rnd = random.Random(1)
    docs = [int(rnd.expovariate(1 / 900)) + 1 for _ in range(3000)] + [9000, 4096, 1, 4097]
    waste, pieces = {}, {}
    for fill in (True, False):
        p, rows = packing.Packer(0, fill=fill), []
        for k, n in enumerate(docs):
            rows += p.add(k, bytes(4 * n))
        rows += p.close()
        size, parts = collections.Counter(), collections.defaultdict(list)
        for r in rows:
            assert r[6] == size[r[5]]  # gapless, in order
            size[r[5]] += r[2]
            parts[r[0]].append((r[1], r[2]))
        for k, n in enumerate(docs):  # each id in exactly one piece
            at = 0
            for start, length in sorted(parts[k]):
                assert start == at
                at += length
            assert at == n
        waste[fill], pieces[fill] = sum(packing.padded(n) - n for n in size.values()) / sum(docs), len(rows) / len(docs)
    assert waste[True] == 0 and 0.05 < waste[False] < 0.4
    assert pieces[True] < 1.7 and pieces[False] < 1.05


def test_packing_bins_are_harmonic():
    """A full bin of class j begins with j whole documents of lengths in (capacity/(j+1), capacity/j]."""
    rnd, p, rows = random.Random(5), packing.Packer(0), []
    docs = [rnd.randint(1, 4096) for _ in range(4000)]
    for k, n in enumerate(docs):
        rows += p.add(k, bytes(4 * n))
    bins = collections.defaultdict(list)
    for r in rows:
        bins[r[5]].append(r)
    assert len(bins) > 1000
    for held in bins.values():
        j = held[0][7]
        assert sum(r[2] for r in held) == packing.CAPACITY
        assert len(held) >= j and all(packing.CAPACITY // r[2] == j for r in held[:j])
        assert all(r[1] + r[2] == r[4] for r in held[:j])  # up to the document's end: no cut but where a gap took its head
        assert all(r[1] == 0 for r in held[j:])


def test_vector_search(spark):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(600, 16)).astype(np.float32)
    x[40] *= 4
    x[50] = x[40]
    x[41] = x[40]
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(900, None), (920, [0.0] * 16), (940, [float("nan")] * 16), (960, [None] * 16), (980, [1.0]), (None, [1.0] * 16)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    got = vector_search.nearest(df, k=10, every=20, shard_rows=256).collect()
    want = vector_search.nearest_exact(df.where("vec_id < 600"), k=10, every=20).collect()
    a, b = {(r.query_id, r.vec_id) for r in got}, {(r.query_id, r.vec_id) for r in want}
    assert len(got) == len(want) and len(a & b) >= 0.9 * len(b)
    d = x.astype(np.float64)
    for r in got:
        assert r.score == pytest.approx(float(d[r.query_id] @ d[r.vec_id]), abs=1e-12)
    ties = sorted((r.rank, r.vec_id) for r in got if r.query_id == 40)[:2]
    assert {v for _, v in ties} <= {41, 50} and ties[0][1] < ties[1][1]
    assert vector_search.nearest(df.where("false")).count() == 0


def test_vector_search_counts_before_it_verifies(spark, sf):
    """On the given table: recall against brute force, and how much was looked at for it."""
    df = spark.read.parquet(f"{sf}/embeddings.parquet")
    got, want = vector_search.nearest(df).collect(), vector_search.nearest_exact(df).collect()
    found, true = {(r.query_id, r.vec_id) for r in got}, {(r.query_id, r.vec_id) for r in want}
    assert len(got) == len(want) and len(found & true) >= 0.9 * len(true)
    seen = {r.query_id: r.n_verified for r in got}
    assert sum(seen.values()) < 0.6 * len(seen) * df.count()
    rng = np.random.default_rng(1)  # a clustered table needs far less
    centres = rng.normal(size=(60, 32))
    x = centres[rng.integers(0, 60, 3000)] + 0.15 * rng.normal(size=(3000, 32))
    near = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x / np.linalg.norm(x, axis=1)[:, None])], "vec_id long, embedding array<double>")
    got, want = vector_search.nearest(near).collect(), vector_search.nearest_exact(near).collect()
    found, true = {(r.query_id, r.vec_id) for r in got}, {(r.query_id, r.vec_id) for r in want}
    seen = {r.query_id: r.n_verified for r in got}
    assert len(found & true) >= 0.9 * len(true) and sum(seen.values()) < 0.15 * len(seen) * 3000


def test_vectors_of_two_lengths(spark):
    rng = np.random.default_rng(2)
    rows = [(i, rng.normal(size=8 + 4 * (i % 2)).tolist()) for i in range(100)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got, want = ({(r.query_id, r.vec_id) for r in f(df, k=3, every=10).collect()} for f in (vector_search.nearest, vector_search.nearest_exact))
    assert len(got) == 30 and len(got & want) >= 27 and all(a % 2 == b % 2 for a, b in got)


def test_suffix_dedup(docs, empty):
    got = {(r.doc_id, r.kept_sha256): r for r in suffix_dedup.cut_repeats(docs).collect()}
    rows = [(r.doc_id, (r.text or "").encode()) for r in docs.collect()]
    first = {}
    for i, t in rows:
        if i is not None:
            for p in range(len(t) - 49):
                first[t[p : p + 50]] = min(first.get(t[p : p + 50], i), i)
    for i, t in rows:
        off = bytearray(len(t))
        for p in range(len(t) - 49):
            if i is not None and first[t[p : p + 50]] < i:
                off[p : p + 50] = b"\1" * 50
        kept = bytes(c for c, o in zip(t, off, strict=True) if not o)
        r = got[i, hashlib.sha256(kept).hexdigest()]
        assert r.n_bytes == len(t) and r.n_removed == sum(off) and bytes(r.kept) == kept
        assert r.n_spans == sum(1 for k, o in enumerate(off) if o and (k == 0 or not off[k - 1]))
    assert suffix_dedup.cut_repeats(empty).count() == 0


def test_loser_tree_orders_and_counts_prefixes():
    rnd = random.Random(5)
    runs, every = [], []
    for _ in range(9):
        rows = sorted((bytes(rnd.choice(b"ab") for _ in range(rnd.randint(16, 50))), b"", rnd.randint(0, 9), 0) for _ in range(40))
        every += [r[0].ljust(50, b"\0") for r in rows]
        runs.append(suffix_dedup.read_run(suffix_dedup.front_code(rows, 50), 0, 50))
    last = None
    out = list(suffix_dedup.merge_runs(runs))
    assert [r[2].ljust(50, b"\0") for r in out] == sorted(every)
    for r in out:
        s = r[2].ljust(50, b"\0")
        if last is not None:
            lcp = next((k for k in range(50) if s[k] != last[k]), 50)
            assert min(r[1], 50) == lcp
        last = s


def test_language(spark, docs, empty):
    rnd = random.Random(2)
    rows = [(i, words(rnd, 40, "abcdefg" if i % 2 else "nopqrst"), ["xx", "yy"][i % 2], "s", 1, "") for i in range(60)]
    df = spark.createDataFrame(rows, KIND)
    got = language_id.identify(df).collect()
    assert all(r.lang_pred == ["xx", "yy"][r.doc_id % 2] and 0 <= r.score <= 1 for r in got)
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) for r in got)
    by = {r.doc_id: r for r in language_id.identify(docs).collect()}
    assert by[0].lang_pred == by[1].lang_pred == by[3].lang_pred == "und" and by[4].lang_pred in ("en", "de")
    assert language_id.identify(empty).count() == 0
    assert language_id.identify(docs.withColumn("lang", F.lit(None).cast("string"))).where("lang_pred <> 'und'").count() == 0


def test_language_against_brute_force(spark):
    """Prototypes and cosines made one n-gram at a time."""
    rnd = random.Random(4)
    rows = [(i, words(rnd, 12, ("abcde", "cdefg", "êtùxy")[i % 3]) + rnd.choice(["", " 12!", "\n"]), f"l{i % 3}", "s", 1, "") for i in range(45)]
    code, place = language_id._tables()

    def vector(text):
        v, symbols = np.zeros(language_id.DIM), [0]
        for c in text:
            k = int(code[ord(c)])
            if k or symbols[-1]:
                symbols.append(k)
        symbols.append(0)
        for i in range(len(symbols) - 2):
            v += place[0][symbols[i]].astype(int) * place[1][symbols[i + 1]] * place[2][symbols[i + 2]]
        return v

    held = lambda i: zlib.crc32(str(i).encode()) % 4 == 2
    profile = {}
    for i, t, lang, *_ in rows:
        if not held(i):
            profile[lang] = profile.get(lang, 0) + vector(t)
    unit = lambda v: v / np.sqrt((v * v).sum())
    got = {r.doc_id: r for r in language_id.identify(spark.createDataFrame(rows, KIND)).collect()}
    for i, t, *_ in rows:
        cos = {k: float(unit(v) @ unit(vector(t))) for k, v in profile.items()}
        best = max(sorted(cos), key=lambda k: round(cos[k], 9))
        assert got[i].lang_pred == best and got[i].score == pytest.approx(max(0, cos[best]), abs=0.02)


def test_url_filter(spark):
    urls = [None, "no scheme", "http://A.Example.NET/en/x?q", "https://example.com/de/", "http://xexample.com/de/a", "ftp://a.org/fr/b#c", "http://a.net", "http://a.net/", "http://h.io/a"] + ["http://bad.io/x"] * 30
    pages = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")
    labels = spark.createDataFrame([(i, 0) for i in range(9, 39)] + [(8, 1), (8, 1), (7, None)], "doc_id long, quality int")
    by = {r.page_id: r for r in url_filter.judge(pages, labels).collect()}
    assert len(by) == len(urls)
    assert (by[0].host, by[0].path, by[1].host) == ("", "", "")
    assert (by[2].host, by[2].path, by[2].rule, by[2].verdict) == ("a.example.net", "/en/x", "example.net/en/", "allow")
    assert by[3].rule == "example.com/de/" and by[4].rule is None and by[5].rule == "org/fr/"
    assert by[6].rule is None and by[7].rule == "net/" and by[7].verdict == "block"
    assert by[9].verdict == "block" and by[8].verdict == "allow"
    assert url_filter.judge(pages, labels.where("false")).where("rule is null and verdict = 'block'").count() == 0
    assert url_filter.judge(pages.where("false"), labels).count() == 0


def test_lm_scores(docs, empty):
    got = {(r.doc_id, r.n_tokens): r for r in lm_scoring.score_documents(docs, PATH).collect()}
    rows = [(r.doc_id, (r.text or "").encode().lower().split()) for r in docs.collect()]
    count = collections.Counter()
    for i, w in rows:
        if not lm_scoring.held_out(i):
            count.update([*w, b""])
    n, v = sum(count.values()), len(count)
    for i, w in rows:
        r = got[i, len(w) + 1]
        assert r.train_tokens == n and r.n_known == sum(count[x] > 0 for x in [*w, b""])
        assert r.base_score == pytest.approx(sum(np.log10((count[x] + 1) / (n + v + 1)) for x in [*w, b""]))
        assert r.score < 0 and np.isfinite(r.score)
    assert got[6, 4].score == pytest.approx(got[7, 4].score, abs=1e-2)
    assert lm_scoring.score_documents(empty, PATH).count() == 0


def test_score_against_brute_force(spark, monkeypatch):
    """A text's score made one place at a time from the fitted model; held-out text against the word counts."""
    from ngramlake.llm import attention as att

    rnd = random.Random(11)
    syllables = ["ba", "ko", "ti", "mu", "re", "la", "son", "tir"]
    word = lambda: "".join(rnd.choice(syllables) for _ in range(rnd.randint(1, 4)))
    rows = [(i, " ".join(word() for _ in range(120))) for i in range(160)]
    made = []
    fit = lm_scoring.fit
    monkeypatch.setattr(lm_scoring, "fit", lambda *a: made.append(fit(*a)) or made[-1])
    got = {r.doc_id: r for r in lm_scoring.score_documents(spark.createDataFrame(rows, "doc_id long, text string"), PATH).collect()}
    of, inside, raw = made[0]
    w, encoder = att.unflatten(raw), common.WordEncoder.get(PATH)
    end = encoder.tokenizer.token_to_id(lm_scoring.END_TEXT)
    for i, t in rows[:3]:
        ids = [end, *encoder.tokenizer.encode(t, add_special_tokens=False).ids, end]
        total = 0.0
        for at in range(1, len(ids)):  # the window of this goal's block of places
            block = (at - 1) // att.STRIDE * att.STRIDE
            first = max(0, block - att.OVERLAP)
            seen = ids[first:at]
            x = np.array([w["by_class"][of[k]] + w["by_hash"][k % att.HASHED] + w["by_place"][p - block + att.OVERLAP] for p, k in enumerate(seen, first)], np.float64)
            s = (x @ w["k"]) @ (x[-1] @ w["q"]) / np.sqrt(att.DIM)
            a = np.exp(s - s.max())
            h = x[-1] + (a / a.sum()) @ (x @ w["v"]) @ w["o"]
            y = h @ w["u"] + w["b"]
            total += y[of[ids[at]]] - np.log(np.exp(y - y.max()).sum()) - y.max() + inside(np.array(ids[at - 1 : at]), np.array(ids[at : at + 1]))[0]
        assert got[i].score == pytest.approx(total / np.log(10), abs=1e-2)


def test_held_out_texts_score_better_than_by_word_counts(spark):
    """On the largest given table; on smaller ones the word counts still win (README)."""
    docs = spark.read.parquet("/root/testdata/sf0.1/documents.parquet")
    held = lm_scoring.score_documents(docs, PATH).where("held_out").agg(F.sum("score"), F.sum("base_score")).first()
    assert held[0] > held[1]


def test_hashes_squeeze_and_back():
    x = np.sort(np.random.default_rng(1).integers(0, 1 << 64, 1000, np.uint64))
    for part in (x, x[:1], x[:0]):
        assert (lm_scoring.unsqueeze(lm_scoring.squeeze(part)) == part).all()
    assert len(lm_scoring.squeeze(x)) < 7.4 * len(x)


def test_ids_in_class_are_a_distribution():
    from ngramlake.llm import attention as att

    rng, n = np.random.default_rng(3), 300
    of = np.concatenate([[0], 1 + np.arange(n - 1) % (att.CLASSES - 1)])
    counts, rank = rng.integers(0, 50, n), np.full(n, -1)
    rank[rng.permutation(n)[:120]] = np.arange(120)
    inside = lm_scoring.InClass(of, counts, rank, rng.integers(0, 3, (lm_scoring.TOP, lm_scoring.TOP)).astype(np.float32))
    for before in range(0, n, 17):
        p = np.exp(inside(np.full(n, before), np.arange(n)).astype(np.float64))
        assert np.allclose(np.bincount(of, p), 1, atol=1e-4)


def test_model_is_a_distribution_and_scores_once():
    from ngramlake.llm import attention as att

    rng = np.random.default_rng(0)
    of = np.concatenate([[0], 1 + np.arange(299) % (att.CLASSES - 1)])
    w = att.fresh()
    ids = np.array([0, *rng.integers(1, 300, 70), 0, 0, 5, 0])
    starts = np.array([0, 72, 75])
    x, real, goal, use, text = att.windows(ids, starts)
    assert use.sum() == len(ids) - 2 and sorted(set(text)) == [0, 1]
    total = np.zeros(goal.shape)
    for c in range(att.CLASSES):
        member = np.flatnonzero(of == c)
        if len(member):
            total += np.exp(att.class_log_probs(w, x, real, np.full_like(goal, member[0]), of))
    assert np.allclose(total[use], 1, atol=1e-4)
    m, loss = {}, []
    nxt = np.concatenate([x[:, 1:], goal[:, -1:]], 1)
    known = np.concatenate([real[:, :-1] & real[:, 1:], use[:, -1:]], 1)
    for t in range(1, 40):
        loss.append(att.step(w, m, t, x, real, nxt, known, of, 0.01))
    assert loss[-1] < loss[0]
    assert att.flatten(att.unflatten(att.flatten(w))) == att.flatten(w)


def test_near_duplicates(spark, docs, empty):
    got = near_dedup.near_duplicates(docs).collect()
    fps = sorted({int(r.fingerprint, 16) for r in got})
    parent = {f: f for f in fps}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in fps:
        for b in fps:
            if (a ^ b).bit_count() <= 2:
                parent[find(a)] = find(b)
    least = {}
    for r in got:
        if r.doc_id is not None:
            f = find(int(r.fingerprint, 16))
            least[f] = min(least.get(f, r.doc_id), r.doc_id)
    assert all(r.component_id == least.get(find(int(r.fingerprint, 16))) for r in got)
    assert len(got) == docs.count()
    native = spark.createDataFrame([("a b c",)], "s string").select(F.xxhash64("s")).first()[0] % 2**64
    assert int(near_dedup.shingle_hashes(b"A b\tC")[0]) == native
    assert near_dedup.fingerprint(b"") == 0
    assert near_dedup.near_duplicates(empty).count() == 0
    assert {r.doc_id for r in near_dedup.keep_one(docs).collect()} == {r.component_id for r in got}


def test_links_of_large_groups(spark):
    rnd = random.Random(4)
    base = [rnd.getrandbits(64) for _ in range(6)]
    fps = {b ^ (1 << rnd.randrange(64)) ^ (1 << rnd.randrange(64)) for b in base for _ in range(40)} | set(base)
    df = spark.createDataFrame([(i, int(np.array([f], np.uint64).view(np.int64)[0])) for i, f in enumerate(sorted(fps))], "doc_id long, fp long")
    rows = lambda small: sorted(map(tuple, near_dedup.components(near_dedup.links(df, small=small)).collect()))
    assert rows(1) == rows(10_000) and rows(1)


def test_media(docs, empty):
    rows = media.media_columns(docs, "doc_id", "text").collect()
    text = collections.defaultdict(list)
    for r in docs.collect():
        text[r.doc_id].append((r.text or "").encode())
    for r in rows:
        raw = next(t for t in text[r.id] if len(t) == r.n_bytes)
        pay = media.padded(raw)
        assert media.from_wav(bytes(r.media)) == pay and len(pay) % 64 == 0 and pay[: len(raw)] == raw
        assert r.payload_sha256 == hashlib.sha256(pay).hexdigest() and r.tail_crc32 == zlib.crc32(pay[-64:])
        assert r.media_sha256 == hashlib.sha256(bytes(r.media)).hexdigest() and r.media_bytes == len(r.media)
    by = collections.defaultdict(set)
    for r in rows:
        by[r.payload_sha256].add(tuple(r.pairs))
        assert r.pairs_sha256 == hashlib.sha256(np.array(r.pairs, "<i8").tobytes()).hexdigest()
    assert all(len(v) == 1 for v in by.values())
    assert media.media_columns(empty, "doc_id", "text").count() == 0


def test_media_fingerprint_against_brute_force():
    """Transforms, peaks and pairs one number at a time; the tail of a payload counts."""
    pay = media.padded(words(random.Random(8), 120).encode())
    x = [b - 128.0 for b in pay]
    x += [0.0] * ((max(0, 256 - len(x)) or -(len(x) - 256) % 128))
    frames = [np.array(x[a : a + 256], np.float32) for a in range(0, len(x) - 255, 128)]
    m = [np.round(np.abs(np.fft.rfft((f - f.mean()) * np.hanning(256).astype(np.float32))).astype(np.float32), 2) for f in frames]
    peaks = []
    for t, row in enumerate(m):
        for k in range(1, len(row) - 1):
            v, up, down = row[k], m[t - 1][k] if t else 0, m[t + 1][k] if t + 1 < len(m) else 0
            if v > row[k - 1] and v >= row[k + 1] and v > up and v >= down and v > media.ABOVE * row.mean():
                peaks.append((t, k))
    want = sorted(t << 22 | k << 14 | k2 << 6 | t2 - t for i, (t, k) in enumerate(peaks) for t2, k2 in peaks[i + 1 : i + 1 + media.FAN] if t2 - t < 64)
    got = media.fingerprint(pay).tolist()
    assert len(want) > 20 and len(set(got) ^ set(want)) <= 0.02 * len(want)  # single against double precision at ties
    long = words(random.Random(9), 100).encode()[:448]
    assert media.fingerprint(long).tolist() != media.fingerprint(long[:384] + bytes(range(64))).tolist()


def test_media_blocks_do_not_change_peaks(monkeypatch):
    raw = words(random.Random(3), 3000).encode()
    whole = media.fingerprint(media.padded(raw)).tolist()
    monkeypatch.setattr(media, "BLOCK", 7)
    assert media.fingerprint(media.padded(raw)).tolist() == whole and whole


def test_mixing(spark, docs, empty):
    rnd = random.Random(6)
    rows = [(i, words(rnd, rnd.randint(1, 60)), "en", f"s{i % 7}" if i % 11 else None, 1, "") for i in range(700)]
    df = spark.createDataFrame(rows, KIND)
    plan = mixing.plan(df).collect()
    size = collections.Counter()
    for r in rows:
        size[r[3]] += len(r[1].split())
    names = sorted((s for s in size if s is not None)) + [None]
    weight = {s: (3, 1, 2)[k % 3] for k, s in enumerate(names)}
    target, left, open_ = {}, 1.5 * sum(size.values()), list(names)
    while True:
        share = {s: left * weight[s] / sum(weight[x] for x in open_) for s in open_}
        over = [s for s in open_ if share[s] > 2 * size[s]]
        if not over:
            target |= share
            break
        for s in over:
            target[s] = 2 * size[s]
            left -= target[s]
            open_.remove(s)
    taken, source = collections.Counter(), {r[0]: r[3] for r in rows}
    for r in plan:
        s = source[r.doc_id]
        assert r.target == pytest.approx(target[s]) and r.source_size == size[s] and 0 <= r.taken <= 2 * r.size
        taken[s] += r.taken
    assert all(abs(taken[s] - target[s]) <= 0.03 * target[s] + 60 for s in names)
    again = {(r.doc_id, r.taken) for r in mixing.plan(df).collect()}
    assert again == {(r.doc_id, r.taken) for r in plan}
    mixed = mixing.mixed_documents(df).groupBy("doc_id").count().collect()
    by = {r.doc_id: r for r in plan}
    assert {r.doc_id: r["count"] for r in mixed} == {i: r.copies for i, r in by.items() if r.copies}
    assert mixing.plan(empty).count() == 0 and mixing.mixed_documents(empty).count() == 0
    assert len(mixing.plan(docs).collect()) == docs.count()


def edit_distance(a, b):
    p = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        q = [i]
        for j, y in enumerate(b, 1):
            q.append(min(p[j] + 1, q[-1] + 1, p[j - 1] + (x != y)))
        p = q
    return p[-1]


def test_edit_join_parts():
    rnd = random.Random(3)
    for _ in range(1500):
        a, b = (bytes(rnd.choice(b"ab") for _ in range(rnd.randint(0, 12))) for _ in range(2))
        assert line_dedup.within(a, b) == (edit_distance(a, b) <= 2)
    for _ in range(1500):
        a = bytes(rnd.choice(b"abcd") for _ in range(rnd.randint(24, 40)))
        b = bytearray(a)
        for _ in range(rnd.randint(0, 2)):
            op, p = rnd.choice("sid"), rnd.randrange(len(b))
            if op == "s":
                b[p] = rnd.choice(b"xyz")
            elif op == "d":
                del b[p]
            else:
                b.insert(p, rnd.choice(b"xyz"))
        s, long = sorted((a, bytes(b)), key=len)
        assert set(line_dedup.line_keys(s, {})[0]) & set(line_dedup.line_keys(long, {})[1])
        x = line_dedup.sketches([a, bytes(b)])
        assert int(x[0] ^ x[1]).bit_count() <= 4


def test_line_dedup(spark, docs, empty):
    rnd = random.Random(9)
    line = [words(rnd, 8) + " end" for _ in range(5)]
    rows = [(1, "\n".join(line[:3]), "en", "s", 1, ""), (2, line[0][:-1] + "X\nshort\n" + line[3], "en", "s", 1, ""), (3, "ab" + line[0] + "\n" + line[4] + "\n" + line[4], "en", "s", 1, ""), (None, "\n" + line[4], "en", "s", 1, "")]
    df = spark.createDataFrame(rows, KIND).unionByName(docs.where("doc_id is not null").withColumn("doc_id", F.col("doc_id") + 100))
    got = line_dedup.dedup_lines(df).collect()
    texts = [(-(1 << 63) if r.doc_id is None else r.doc_id, r.text.encode().split(b"\n")) for r in df.collect() if r.text is not None]
    first = {}
    for i, t in texts:
        for k, x in enumerate(t):
            if len(x) >= line_dedup.LEAST:
                first[x] = min(first.get(x, (i, k)), (i, k))
    parent = {x: x for x in first}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    every = sorted(first)
    for a in every:
        for b in every:
            if a < b and abs(len(a) - len(b)) <= 2 and len(a) < 2000 and edit_distance(a, b) <= 2:
                parent[find(a)] = find(b)
    keep = {}
    for x in every:
        keep[find(x)] = min(keep.get(find(x), first[x]), first[x])
    want = collections.Counter()
    for i, t in texts:
        want[i, b"\n".join(x for k, x in enumerate(t) if len(x) < line_dedup.LEAST or keep[find(x)] == (i, k)).decode()] += 1
    have = collections.Counter((-(1 << 63) if r.doc_id is None else r.doc_id, r.text) for r in got if r.text is not None)
    assert have == want
    assert len(got) == df.count() and got[0].asDict().keys() >= {"n_lines", "n_removed", "score"}
    assert line_dedup.dedup_lines(empty).count() == 0


def test_chunk_rows_round_trip(docs):
    rows = common.to_chunks(docs, "doc_id", "text", "t").collect()
    back = [x for r in rows for x in zip(*common.open_chunk(r["n"], bytes(r["ids"]), bytes(r["known"]), bytes(r["lens"]), bytes(r["payload"])), strict=True)]
    assert collections.Counter(back) == collections.Counter((r.doc_id, (r.text or "").encode()) for r in docs.collect())


def test_hosts_without_labels_take_their_domain(spark):
    urls = [f"http://s{i % 40}.bad.io/x" for i in range(400)] + [f"http://s{i % 40}.good.de/x" for i in range(400)]
    fresh = ["http://new.bad.io/", "http://other.io/", "http://new.good.de/", "http://else.where/"]
    pages = spark.createDataFrame(list(enumerate(urls + fresh)), "page_id long, url string")
    labels = spark.createDataFrame([(i, int(i >= 400)) for i in range(800)], "doc_id long, quality int")
    by = {r.page_id: r.verdict for r in url_filter.judge(pages, labels).collect()}
    assert [by[i] for i in range(800, 804)] == ["block", "block", "allow", "allow"] and len(by) == 804
    hosts = spark.createDataFrame([("new.bad.io",), ("s1.bad.io",)], "host string")
    rows = url_filter.host_of(F.col("url")).alias("host")
    labelled = pages.join(labels, F.col("page_id") == F.col("doc_id")).select(rows, (1.0 - F.col("quality")).alias("bad"))
    got = {r.host: r for r in url_filter.reputation(labelled, hosts)[0].collect()}
    own = {r.host: r for r in url_filter.reputation(labelled)[0].collect()}
    assert got["s1.bad.io"] == own["s1.bad.io"] and (got["new.bad.io"].n, got["new.bad.io"].bad) == (0, 0.0) and got["new.bad.io"].mean > 0.9


def test_equal_short_lines_go(spark):
    rows = [(1, "short\n\na\nshorx"), (2, "a\nshort\n\n\nkept"), (3, "a"), (None, "kept\nlast"), (4, None)]
    got = {r.doc_id: (r.text, r.n_removed) for r in line_dedup.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string"), exact=1).collect()}
    assert got == {1: ("short\n\na\nshorx", 0), 2: ("\n", 3), 3: ("", 1), None: ("kept\nlast", 0), 4: (None, 0)}


def test_pipeline_cuts_short_lines(spark):
    corpus_pipeline = pytest.importorskip("corpus_pipeline")
    docs = spark.createDataFrame([(1, "same", "en", "s", 4), (2, "same\nother", "en", "s", 10)], KIND.removesuffix(", score string"))
    assert {(r.doc_id, r.text, r.n_chars) for r in corpus_pipeline.line_stage(spark, docs, "").collect()} == {(1, "same", 4), (2, "other", 5)}


def test_keep_one_by_component_not_by_id(spark):
    rnd = random.Random(3)
    a, b, c, d = (words(rnd, 40) for _ in range(4))
    rows = [(None, a), (None, b), (None, a), (7, c), (7, d), (7, c), (8, c), (9, None), (9, "")]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = sorted(((r.doc_id, r.text or "") for r in near_dedup.keep_one(df).collect()), key=str)
    assert got == sorted([(None, a), (None, b), (7, c), (7, d), (9, "")], key=str)


def test_every_chunk_trains_and_counts(spark):
    from ngramlake.llm import attention as att

    share, rng = lm_scoring.SHARE * lm_scoring.BATCH, random.Random(2)
    sizes, passed, steps = [rng.randint(0, 9000) for _ in range(40)], 0, 0
    for n in sizes:  # groups too small for a step of their own
        steps += lm_scoring.due(passed, n)
        passed += n
    assert steps == -(-sum(sizes) // share)
    # partial sums count by their steps
    one, two = att.fresh(), {k: v + 1 for k, v in att.fresh().items()}
    row = lambda s, w: lm_scoring.pa.RecordBatch.from_pydict({"level": [0], "steps": [s], "weights": [att.flatten(w)]})
    (got,) = lm_scoring._average([row(1, one), row(3, two)])
    assert got.column(1)[0].as_py() == 4 and np.allclose(att.unflatten(got.column(2)[0].as_py())["b"], 0.75)
    assert list(lm_scoring._average([])) == []


def test_classes_read_every_training_text(spark):
    from ngramlake.llm import attention as att

    rnd = random.Random(8)
    texts = [(i, words(rnd, 30)) for i in range(400)] + [(400, None), (None, "one two three")]
    df = spark.createDataFrame(texts, "doc_id long, text string").repartition(3)
    chunks = common.to_chunks(df, "doc_id", "text", "t", lm_scoring._pack(PATH), names=("extra", "words", "names"), keep=False)
    encoder = common.WordEncoder.get(PATH)
    vocab, end = encoder.tokenizer.get_vocab_size(), encoder.tokenizer.token_to_id(lm_scoring.END_TEXT)
    rank = np.full(vocab, -1)
    counts, before = lm_scoring.id_counts(chunks, vocab)
    rank[np.argsort(-counts, kind="stable")[:50]] = np.arange(50)
    of, pairs = lm_scoring.classes(chunks, vocab, end, rank)
    train = [(t or "").encode() for i, t in texts if not lm_scoring.held_out(i)]
    ids, starts = lm_scoring._subwords(encoder, train, end)
    seen, both, goals = np.zeros((vocab, 2 * att.NEAR)), np.zeros_like(pairs), np.zeros(vocab, int)
    for a, b in zip(starts[:-1], starts[1:], strict=True):
        for x, y in zip(ids[a : b - 1], ids[a + 1 : b], strict=True):
            seen[y, x % att.NEAR] += 1
            seen[x, att.NEAR + y % att.NEAR] += 1
            goals[y] += 1
            if rank[x] >= 0 and rank[y] >= 0:
                both[rank[x], rank[y]] += 1
    assert (goals == counts).all() and (both == pairs).all() and both.sum() > 100
    assert (of == att.cluster(*att.project(seen), end)).mean() > 0.999
    assert len(before) == chunks.count() and min(before.values()) == 0


def test_lines_of_rows_that_share_an_id(spark):
    """A document is its id and its text: rows of one id neither hide nor answer for each other."""
    rnd = random.Random(12)
    r, other = words(rnd, 9), words(rnd, 9)
    q = r[:-1] + ("X" if r[-1] != "X" else "Y")  # one edit from r
    p = q[:10] + words(rnd, 9)[: len(q) - 10].ljust(len(q) - 10, "k")  # shares a segment with q only
    count = lambda df: collections.Counter((x.doc_id, x.text) for x in line_dedup.dedup_lines(df, report=False).collect())
    kind = "doc_id long, text string"
    for rows, want in (
        ([(1, r), (5, q), (5, p)], [(1, r), (5, ""), (5, p)]),
        ([(1, r), (5, p), (5, q)], [(1, r), (5, ""), (5, p)]),
        ([(1, r), (2, q), (2, other)], [(1, r), (2, ""), (2, other)]),
        ([(None, r), (None, other), (None, None), (3, q)], [(None, r), (None, other), (None, None), (3, "")]),
        ([(4, r), (4, r), (6, r)], [(4, r), (4, r), (6, "")]),
    ):
        assert count(spark.createDataFrame(rows, kind).repartition(3)) == collections.Counter(want)


def test_lines_with_equal_sketches(spark):
    """Lines of the same bytes in another order are no copies."""
    a = "alpha beta gamma delta epsilon zeta"
    rows = [(1, a), (2, a + "!"), (3, "gamma beta alpha delta epsilon zeta"), (4, "zeta epsilon delta gamma beta alpha")]  # equal sketches but for 2
    got = {r.doc_id: r.text for r in line_dedup.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {1: a, 2: "", 3: rows[2][1], 4: rows[3][1]}


def test_clashing_and_further_columns(spark):
    """Every operator on a table whose other columns bear its own names."""
    rnd = random.Random(13)
    rows = [(i, words(rnd, 30), ["en", "de"][i % 2], f"s{i % 2}") for i in range(12)] + [(None, None, None, None), (3, "", "en", "s0")]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    for name in ("sequence_id", "offset", "score", "component_id", "fp", "label", "size", "target", "taken", "bucket", "chunk", "n_removed", "line_doc", "stay", "rate", "s", "n", "bad"):
        df = df.withColumn(name, F.lit(name))
    n = len(rows)
    assert packing.pack_documents(df, PATH).select("doc_id").distinct().count() == 13
    assert suffix_dedup.cut_repeats(df).count() == n and language_id.identify(df).count() == n
    assert lm_scoring.score_documents(df, PATH).count() == n and near_dedup.near_duplicates(df).count() == n
    assert media.media_columns(df, "doc_id", "text").count() == n and mixing.plan(df).count() == n
    kept = line_dedup.dedup_lines(df)
    assert kept.count() == n and set(df.columns) < set(kept.columns)
    assert near_dedup.keep_one(df).columns == df.columns
    vec = spark.createDataFrame([(i, [float(i + 1), 1.0]) for i in range(5)], "vec_id long, embedding array<double>")
    for name in ("block", "shard", "lane", "d", "x", "v", "score", "rank"):
        vec = vec.withColumn(name, F.lit(name))
    assert vector_search.nearest(vec).count() == 4
    pages = spark.createDataFrame([(1, "http://a.b/c")], "page_id long, url string").withColumn("host", F.lit("h")).withColumn("bad", F.lit(1)).withColumn("doc_id", F.lit(9))
    labels = spark.createDataFrame([(1, 1)], "doc_id long, quality int").withColumn("page_id", F.lit(3)).withColumn("host", F.lit("x"))
    assert [r.host for r in url_filter.judge(pages, labels).collect()] == ["a.b"]


def test_texts_longer_than_a_chunk(spark, monkeypatch):
    monkeypatch.setattr(suffix_dedup, "TEXT_BYTES", 4000)
    monkeypatch.setattr(lm_scoring, "TEXT_BYTES", 4000)
    rnd = random.Random(14)
    shared = words(rnd, 2000)
    df = spark.createDataFrame([(1, words(rnd, 1500) + shared), (2, shared + words(rnd, 100)), (3, "tiny")], "doc_id long, text string").repartition(2)
    got = {r.doc_id: r.n_removed for r in suffix_dedup.cut_repeats(df).collect()}
    assert got[1] == got[3] == 0 and abs(got[2] - len(shared)) <= 50
    assert {r.doc_id: r.n_tokens for r in lm_scoring.score_documents(df, PATH).collect()} == {r.doc_id: len(r.text.split()) + 1 for r in df.collect()}


def test_beta_tail_quantiles(spark):
    """The closed form against draws."""
    rng = np.random.default_rng(5)
    rows = [(float(a), float(b)) for a in (1, 2, 5, 40, 400) for b in (0.9, 3, 20, 900)]
    for a, b, q in spark.createDataFrame(rows, "a double, b double").select("a", "b", url_filter.beta_tail(F.col("a"), F.col("b"))).collect():
        true = np.quantile(rng.beta(a, b, 400_000), 0.05)
        assert q < true + 0.006 and (b < 1 or true - q < (0.02 if a < 5 else 0.006))  # few good pages: too low, never too high


def test_every_training_window_is_in_one_step(monkeypatch):
    """First weights come from pairs of all training texts; each of their windows is then descended once."""
    from ngramlake.llm import attention as att

    rnd = random.Random(5)
    texts = [" ".join(rnd.choice(["sun", "moon", "sea", "of", "and"]) for _ in range(rnd.randint(0, 90))).encode() for _ in range(1500)]
    encoder = common.WordEncoder.get(PATH)
    vocab, end = encoder.tokenizer.get_vocab_size(), encoder.tokenizer.token_to_id(lm_scoring.END_TEXT)
    rows, want, before, passed = [], [], {}, 0
    for c, lo in enumerate((0, 700, 710)):
        part, ids = texts[lo : (700, 710, 1500)[c]], np.arange(lo, (700, 710, 1500)[c])
        rows.append({"chunk": c, "ids": ids.tobytes(), "known": np.ones(len(ids), np.uint8).tobytes(), "extra": lm_scoring._pack(PATH)(part)[0]})
        x, starts = lm_scoring._subwords(encoder, [t for i, t in zip(ids.tolist(), part, strict=True) if not lm_scoring.held_out(i)], end)
        a, real, *_ = att.windows(x, starts)
        want += [tuple(np.where(r, k, -1)) for k, r in zip(a, real, strict=True)]
        before[c], passed = passed, passed + len(a)
    seen = []
    monkeypatch.setattr(att, "step", lambda w, m, t, ids, real, *a: seen.extend(tuple(np.where(r, k, -1)) for k, r in zip(ids, real, strict=True)))
    of = np.concatenate([[0], 1 + np.arange(vocab - 1) % (att.CLASSES - 1)])
    (got,) = lm_scoring._refine(of, att.flatten(att.fresh()), vocab, before)([lm_scoring.pa.RecordBatch.from_pylist(rows)])
    assert sorted(seen) == sorted(want) and got.column(1)[0].as_py() >= len(want) // lm_scoring.BATCH
    # the start: the class after a class as often as pairs say
    rank = np.full(vocab, -1)
    rank[:3] = np.arange(3)
    pairs = np.zeros((lm_scoring.TOP, lm_scoring.TOP), np.float32)
    pairs[1, 2], pairs[2, 1], pairs[2, 2] = 1000, 250, 750
    w = lm_scoring.first_weights(of, rank, pairs)
    p = np.exp(w["by_class"][of[2]] @ w["u"] + w["b"])
    assert p[of[1]] / p.sum() == pytest.approx(0.25, abs=0.01) and p[of[2]] / p.sum() == pytest.approx(0.75, abs=0.01)


def test_every_training_id_is_one_goal(monkeypatch):
    """Windows overlap, yet each id but a text's first is descended once, ends included; gradients are those of the loss."""
    from ngramlake.llm import attention as att

    rng = np.random.default_rng(2)
    of = np.concatenate([[0], 1 + np.arange(299) % (att.CLASSES - 1)])
    ids, starts = rng.integers(0, 300, 700), np.array([0, 130, 132, 700])
    x, real, goal, use, _ = att.windows(ids, starts)
    goals, step = [], att.step

    def seen(w, m, t, ids, real, goal, use, *a):
        goals.extend(goal[use].tolist())
        return step(w, m, t, ids, real, goal, use, *a)

    monkeypatch.setattr(att, "step", seen)
    assert lm_scoring.train_steps(att.fresh(), {}, 0, x, real, goal, use, of, 3, 0.002) == 3
    assert sorted(goals) == sorted(np.delete(ids, starts[:-1]).tolist())
    w = {k: v * np.float32(3) for k, v in att.fresh().items()}
    loss = lambda: -att.class_log_probs(w, x, real, goal, of)[use].mean(dtype=np.float64)
    mean, g = att._gradients(w, x, real, goal, use, of, int(use.sum()))
    assert mean == pytest.approx(loss(), rel=1e-4)
    for name in att.NAMES:  # along its own gradient
        d, kept = g[name] / np.abs(g[name]).max() * np.float32(0.02), w[name]
        w[name] = kept + d
        up = loss()
        w[name] = kept - d
        assert up - loss() == pytest.approx(2 * float((d * g[name]).sum()), rel=0.05)
        w[name] = kept


def test_chunks_hold_the_ids_and_words_of_their_texts():
    from xxhash import xxh3_64_intdigest

    rnd = random.Random(6)
    texts = [" ".join(rnd.choice(["Sun", "sun", "moon!", "señor,", "x1", "..", "été", " a", "B"]) for _ in range(rnd.randint(0, 40))).encode() for _ in range(50)] + [b"", b" \t", b"A"]
    encoder = common.WordEncoder.get(PATH)
    end = encoder.tokenizer.token_to_id(lm_scoring.END_TEXT)
    extra, words, names = lm_scoring._pack(PATH)(texts)
    ids, starts = lm_scoring._open(extra, 1, encoder.tokenizer.get_vocab_size())
    codes, size = lm_scoring._open_words(words)
    hashes, at = lm_scoring.unsqueeze(names)[codes].tolist(), 0
    for k, t in enumerate(texts):
        assert ids[starts[k] : starts[k + 1]].tolist() == [end, *encoder.tokenizer.encode(t.decode(), add_special_tokens=False).ids, end]
        assert hashes[at : at + size[k]] == [xxh3_64_intdigest(w) for w in [*t.lower().split(), b""]]
        at += size[k]
    assert at == len(hashes)


def test_graphs_give_the_sums_of_numpy(monkeypatch):
    """The graphs against the reference forms, first and last windows of texts and logits that overflow included."""
    from ngramlake.llm import attention as att
    from ngramlake.llm import graphs

    assert att.loops()[0] is graphs.gradients
    rng = np.random.default_rng(4)
    of = np.concatenate([[0], 1 + np.arange(299) % (att.CLASSES - 1)])
    ids, starts = rng.integers(0, 300, 900), np.array([0, 2, 130, 133, 900])
    x, real, goal, use, _ = att.windows(ids, starts)
    for scale in (1, 3, 60):
        w = {k: v * np.float32(scale) for k, v in att.fresh().items()}
        assert np.allclose(graphs.class_log_probs(w, x, real, goal, of)[use], att.class_log_probs(w, x, real, goal, of)[use], rtol=1e-3, atol=1e-4)
        (loss, g), (mean, d) = (f(w, x, real, goal, use, of, int(use.sum())) for f in (graphs.gradients, att._gradients))
        assert loss == pytest.approx(mean, rel=1e-3) and g.keys() == d.keys()
        for name in att.NAMES if scale < 60 else ():
            assert g[name].shape == d[name].shape and np.abs(g[name] - d[name]).max() < 1e-3 * np.abs(d[name]).max()
    # without onnxruntime the numpy forms do the same steps
    made = []
    for there in (True, False):
        monkeypatch.setattr(att, "find_spec", lambda name: there or None)
        att.loops.cache_clear()
        w, m = att.fresh(), {}
        lm_scoring.train_steps(w, m, 0, x, real, goal, use, of, 4, 0.002)
        made.append(w)
    att.loops.cache_clear()
    assert all(np.allclose(made[0][k], made[1][k], atol=1e-4) for k in att.NAMES)


def test_graphs_take_less_time_than_numpy():
    """A step over 256 windows, own processor time, the best of many."""
    import time

    from ngramlake.llm import attention as att
    from ngramlake.llm import graphs

    att.one_thread()
    rng = np.random.default_rng(4)
    of = np.concatenate([[0], 1 + np.arange(299) % (att.CLASSES - 1)])
    x, real, goal, use, _ = att.windows(rng.integers(0, 300, 256 * att.STRIDE + 1), np.array([0, 256 * att.STRIDE + 1]))
    took = {}
    for f in (graphs.gradients, att._gradients):
        for _ in range(20):
            at = time.process_time()
            f(att.fresh(), x, real, goal, use, of, int(use.sum()))
            took[f] = min(took.get(f, 9), time.process_time() - at)
    assert took[graphs.gradients] < 0.8 * took[att._gradients]


def test_words_get_the_ids_of_the_whole_tokenizer():
    """Words met together, in any form."""
    words = ["Sun", "sun", "SUN!", "...", ".", "a.b", "x1", "señor,", "ÉTÉ", "ĦA", "İstanbul", "ǅ", "ΣΑΣ", "ΑΣ.", "straße", "ẞ", "日本", "a\u00a0b", "\u2003", "don't", "--", "(word)", "word)", "\ufffd"]
    raw = [*(w.encode() for w in words), b"\xff", b"ab\xc3"]
    encoder = common.WordEncoder(PATH)
    want = [np.array(encoder.tokenizer.encode(w.decode("utf-8", "replace"), add_special_tokens=False).ids, "<u4").tobytes() for w in raw]
    assert encoder.encode_words(raw) == want and encoder.encode_words(raw[:5]) == want[:5] and encoder.encode_words([]) == []
    assert encoder.encode_all([b" ".join(raw), b"", raw[0]]) == [b"".join(want), b"", want[0]]


def test_chunks_after_words_were_forgotten(monkeypatch):
    """A worker that keeps few words makes the same chunks as one that keeps all."""
    rnd = random.Random(12)
    chunks = [[" ".join(rnd.choice("sun SUN moon! sea, señor x1 of".split()) + rnd.choice("abc") for _ in range(rnd.randint(0, 9))).encode() for _ in range(rnd.randint(0, 12))] for _ in range(30)]
    made = []
    for most in (1 << 30, 12, 0):
        monkeypatch.setattr(lm_scoring, "CACHE", most)
        monkeypatch.setattr(lm_scoring.Met, "_own", {})
        made.append([lm_scoring._pack(PATH)(c) for c in chunks])
        (met,) = lm_scoring.Met._own.values()
        assert len(met.code) == len(met.many) == len(met.hashes) and (len(met.code) > 12) == (most > 12 or len(set(b" ".join(chunks[-1]).split())) > 12)
    assert made[0] == made[1] == made[2]
    lm_scoring._pack(PATH).done()  # when a task ends, nothing is kept
    assert not lm_scoring.Met._own and not common.WordEncoder.get(PATH).words
