"""Word vectors, neighbours and information norms.

The default provider sums bucket vectors of a word's character n-grams (3 to 5,
with boundary marks) and of the whole word, so related spellings are near; a digit
string also leans on a common number bucket.  Buckets are rows of an embedding
table, chosen by md5, so any engine gives the same vectors.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SHORT, LONG, NUMBER = 3, 5, "#num"
#: The bucket table is held by every task; larger ones are refused.
TABLE_BYTES = 256 << 20
#: Query tokens whose neighbours one call looks for.
MOST_TOKENS = 200_000


def bucket_matrix(embeddings: DataFrame) -> np.ndarray:
    n, d = embeddings.agg(F.count("*"), F.max(F.size("embedding"))).first()
    if n * (d or 0) * 8 > TABLE_BYTES:
        raise ValueError(f"{n} bucket vectors exceed {TABLE_BYTES} bytes; hash into fewer")
    t = embeddings.orderBy("vec_id").select("embedding").toArrow().column(0)
    return _matrix(t.combine_chunks()).astype(np.float32).astype(np.float64)


def word_grams(word: str) -> list[str]:
    s = f"<{word}>"
    return [s[i : i + n] for n in range(SHORT, LONG + 1) for i in range(len(s) - n + 1)] + [s]


def _bucket(gram: str, n: int) -> int:
    return int(hashlib.md5(gram.encode()).hexdigest()[:8], 16) % n


def word_vectors(words: list[str], buckets: np.ndarray, known: dict[str, int] | None = None) -> np.ndarray:
    """Unit vectors of words; ``known`` keeps the buckets of grams between calls."""
    n = len(buckets)
    known = {} if known is None else known
    rows, sizes = [], []
    for w in words:
        g = word_grams(w)
        for x in g:
            if x not in known:
                known[x] = _bucket(x, n)
        rows += [known[x] for x in g]
        sizes.append(len(g))
    if not words:
        return np.zeros((0, buckets.shape[1]))
    v = np.add.reduceat(buckets[rows].astype(np.float64, copy=False), np.concatenate([[0], np.cumsum(sizes)[:-1]]), axis=0)
    v /= np.maximum(np.sqrt((v * v).sum(1)), 1e-12)[:, None]
    number = np.array([w.isascii() and w.isdigit() for w in words])
    if number.any():
        v[number] += 2 * buckets[_bucket(NUMBER, n)]
        v[number] /= np.sqrt((v[number] ** 2).sum(1))[:, None]
    return v


def lexicon(tokens: DataFrame, embeddings: DataFrame, keep: tuple[str, ...] = ()) -> DataFrame:
    """``token, vec`` by the subword provider, and the columns ``keep``."""
    buckets = bucket_matrix(embeddings)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 2048):
                part = b.slice(at, 2048)
                v = word_vectors(part.column(0).to_pylist(), buckets)
                ends = np.arange(len(v) + 1, dtype=np.int32) * v.shape[1]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.ListArray.from_arrays(ends, v.ravel()), *part.columns[1:]], ["token", "vec", *keep])

    kept = "".join(f", {k} {tokens.schema[k].dataType.simpleString()}" for k in keep)
    return tokens.select("token", *keep).mapInArrow(run, f"token string, vec array<double>{kept}")


def _matrix(vectors: pa.Array) -> np.ndarray:
    """Vectors of one length as rows."""
    flat = vectors.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(len(vectors), -1) if len(vectors) else np.zeros((0, 0))


def neighbors(query_tokens: DataFrame, vocab: DataFrame, embeddings: DataFrame | None, theta: float, table: DataFrame | None = None) -> DataFrame:
    """``tok, nb, cos``: vocabulary tokens of cosine at least ``theta`` to a query token.

    One pass over the vocabulary against the matrix of query tokens.  ``table``
    (``token, vec``) replaces the subword provider by the caller's own vectors.
    """
    asked = sorted(r[0] for r in query_tokens.select("token").distinct().limit(MOST_TOKENS + 1).collect())
    if len(asked) > MOST_TOKENS:
        raise ValueError("too many query tokens for one call; split the queries")
    buckets = None if table is not None else bucket_matrix(embeddings)
    if table is not None:
        own = {r[0]: np.array(r[1], np.float64) for r in table.where(F.col("token").isin(asked)).select("token", "vec").collect()}
        asked = [a for a in asked if a in own]
        q = np.array([own[a] / max(1e-12, math.sqrt((own[a] ** 2).sum())) for a in asked]) if asked else np.zeros((0, 1))
        rows = vocab.select("token").join(table.select("token", "vec"), "token")
    else:
        q = word_vectors(asked, buckets)
        rows = vocab.select("token")
    names = np.array(asked, object)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            words = b.column(0).to_pylist()
            for at in range(0, len(words), 2048):
                part = words[at : at + 2048]
                if buckets is None:
                    v = np.array(b.column(1).slice(at, 2048).to_pylist(), np.float64)
                    v /= np.maximum(np.sqrt((v * v).sum(1)), 1e-12)[:, None]
                else:
                    v = word_vectors(part, buckets)
                if not len(names) or not len(part):
                    continue
                c = np.round(v @ q.T, 6)
                i, j = np.nonzero(c >= theta)
                yield pa.RecordBatch.from_arrays([pa.array(names[j].tolist(), pa.string()), pa.array([part[k] for k in i], pa.string()), pa.array(c[i, j])], ["tok", "nb", "cos"])

    return rows.mapInArrow(run, "tok string, nb string, cos double")


def neighbors_lsh(query_tokens: DataFrame, vectors: DataFrame, theta: float, bucket: float = 0.5, tables: int = 8) -> DataFrame:
    """Approximate neighbours of (``token, vec``) unit vectors by random projections, re-checked exactly."""
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector

    x = vectors.select("token", array_to_vector("vec").alias("f"), "vec")
    model = BucketedRandomProjectionLSH(inputCol="f", outputCol="h", bucketLength=bucket, numHashTables=tables, seed=3).fit(x)
    q = x.join(query_tokens.select("token").distinct(), "token", "left_semi")
    near = model.approxSimilarityJoin(q, x, math.sqrt(max(0.0, 2 - 2 * theta)) + 1e-9, "dist")
    c = F.round(1 - F.col("dist") * F.col("dist") / 2, 6)
    return near.select(F.col("datasetA.token").alias("tok"), F.col("datasetB.token").alias("nb"), c.alias("cos")).where(F.col("cos") >= theta)


def cooccurrence_vectors(corpus: DataFrame, top: int = 512, dim: int = 64) -> DataFrame:
    """``token, vec`` from positive pointwise mutual information with the ``top`` tokens,
    folded to ``dim`` numbers by a hashed sign projection; SQL functions only."""
    from ngramlake.operators.vocab import ngrams, token_counts

    counts = token_counts(corpus)
    context = counts.orderBy(F.desc("freq"), "token").limit(top).select(F.col("token").alias("c"), F.col("freq").alias("fc"))
    pairs = ngrams(corpus, 2).groupBy("key").agg(F.count("*").alias("n")).select(F.split("key", "\x01").alias("t"), "n")
    both = pairs.select(F.col("t")[0].alias("token"), F.col("t")[1].alias("c"), "n").union(pairs.select(F.col("t")[1], F.col("t")[0], "n")).groupBy("token", "c").agg(F.sum("n").alias("n"))
    total = counts.agg(F.sum("freq").alias("total"))
    pmi = both.join(F.broadcast(context), "c").join(counts, "token").join(F.broadcast(total)).withColumn("w", F.greatest(F.lit(0.0), F.log(F.col("n") * F.col("total") / (2 * F.col("freq") * F.col("fc"))))).where("w > 0")
    sign = lambda k: F.when(F.pmod(F.xxhash64("c", F.lit(k)), F.lit(2)) == 0, 1.0).otherwise(-1.0)
    sums = pmi.groupBy("token").agg(*[F.sum(F.col("w") * sign(k)).alias(f"d{k}") for k in range(dim)])
    return sums.select("token", F.array(*[F.col(f"d{k}") for k in range(dim)]).alias("vec"))


def trained_vectors(corpus: DataFrame, dim: int = 64, seed: int = 1) -> DataFrame:
    """``token, vec`` by the library's skip-gram trainer (depends on the partitioning)."""
    from pyspark.ml.feature import Word2Vec
    from pyspark.ml.functions import vector_to_array

    model = Word2Vec(vectorSize=dim, minCount=2, seed=seed, inputCol="tokens", outputCol="_v").fit(corpus)
    return model.getVectors().select(F.col("word").alias("token"), vector_to_array("vector").alias("vec"))


def whitened_norms(lex: DataFrame, vocab: DataFrame, ridge: float = 1e-6) -> DataFrame:
    """``token, v``: squared norm after whitening with corpus frequencies as weights.

    Weighted sums of x and xx' are added up in the tasks; the driver inverts one
    small matrix.  Independent of any rotation, so no eigenvectors are needed.
    A lexicon that has ``freq`` beside its vectors is not joined; others are, by sorting
    both sides, since vectors are far larger than Spark takes them for.
    """
    if "freq" not in lex.columns:
        lex = lex.join(vocab.select("token", "freq").hint("merge"), "token")
    rows = lex.select("token", "vec", F.col("freq").cast("double").alias("w"))
    kind = "w double, s binary, ss binary"

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w, s, ss = 0.0, 0.0, 0.0
        for b in batches:
            x, p = _matrix(b.column(1)), b.column(2).to_numpy()
            if len(p):
                w, s, ss = w + p.sum(), s + p @ x, ss + (x * p[:, None]).T @ x
        if w:
            yield pa.RecordBatch.from_arrays([pa.array([w]), pa.array([s.tobytes()], pa.binary()), pa.array([ss.tobytes()], pa.binary())], ["w", "s", "ss"])

    total, mean, cov = 0.0, 0.0, 0.0
    for r in rows.mapInArrow(run, kind).toLocalIterator():  # one small matrix a task
        total, mean, cov = total + r["w"], mean + np.frombuffer(bytes(r["s"])), cov + np.frombuffer(bytes(r["ss"]))
    if not total:
        return rows.select("token", F.lit(0.0).alias("v"))
    mean, d = mean / total, len(mean)
    cov = cov.reshape(d, d) / total - np.outer(mean, mean)
    inverse = np.linalg.inv(cov + ridge * np.trace(cov) / d * np.eye(d))

    def norm(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = _matrix(b.column(1)).reshape(-1, d) - mean
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(np.einsum("ij,jk,ik->i", x, inverse, x))], ["token", "v"])

    return rows.select("token", "vec").mapInArrow(norm, "token string, v double")


def norms(vocab: DataFrame, kind: str = "surprisal", lex: DataFrame | None = None) -> DataFrame:
    """``token, v`` by ``surprisal`` (-ln p), ``whitened`` or ``unit``."""
    if kind == "surprisal":
        return vocab.select("token", F.col("surprisal").alias("v"))
    if kind == "unit":
        return vocab.select("token", F.lit(1.0).alias("v"))
    if kind == "whitened":
        return whitened_norms(lex, vocab)
    raise ValueError(f"unknown norm {kind!r}")


def calibrate_penalty(norm: DataFrame, nth: int = 50, m_ref: int = 5) -> float:
    """The constant that makes the factor of the ``nth`` lowest norm 1/e at length ``m_ref``."""
    low = [r[0] for r in norm.orderBy("v", "token").select("v").limit(nth).collect()]
    return (low[-1] if low else float(m_ref)) / m_ref


def insertables(norm: DataFrame, kappa: float, theta: float, m: int) -> DataFrame:
    """Tokens whose single insertion alone keeps a perfect match at ``theta``."""
    return norm.where(F.col("v") <= -m * kappa * math.log(theta))
