"""Soft search: grow patterns one query token at a time, keep what occurs.

A frontier row is a pattern for a query with its sum of costs ``s`` and log penalty
``lp``.  A step joins it with the neighbours of the next query token (a substitution
or the token itself), adds the deletion of that token and, before a substitution,
insertions; drops what scores below the threshold on the query so far; keeps of
each pattern the states none of which is worse in both numbers; and looks up the
distinct patterns.  Scores of prefixes never fall below those of wholes, and
prefixes of occurring patterns occur, so nothing is lost.

A step's candidates and what the lookup finds are written to the shared folder: each
is read more than once, and the lineage of later steps stays short.  Where patterns only
substitute and segments answer, the same steps are taken in the segments' tasks instead
(``operators/walk.py``): a prefix is extended only to what occurs, so candidates are
neither written nor sent to every segment.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ngramlake.functions.similarity import BASE, cost, similarity
from ngramlake.functions.text import SEP, key_of, key_size
from ngramlake.operators import segments, walk
from ngramlake.operators.index import WindowIndex
from ngramlake.operators.lookup import exact_lookup, exists, matching_windows
from ngramlake.sources.tables import spool


@dataclass
class Finder:
    """Exact lookup of ``key``: those that occur with their ``hits``, or (``occur``) those that
    occur alone; patterns of over ``longest`` tokens cannot be asked."""

    hits: Callable[[DataFrame], DataFrame]
    occur: Callable[[DataFrame], DataFrame]
    longest: int
    segments: segments.SegmentIndex | None = None

    def __call__(self, keys: DataFrame) -> DataFrame:
        return self.hits(keys)


def fence_finder(index: WindowIndex) -> Finder:
    return Finder(lambda keys: exact_lookup(keys, index).where("hits > 0"), lambda keys: exists(keys, index), index.length)


def segment_finder(index: segments.SegmentIndex) -> Finder:
    return Finder(lambda keys: segments.hits(keys, index), lambda keys: segments.hits(keys, index).select("key"), index.length, index)


def gram_finder(grams: DataFrame, longest: int = 1 << 30) -> Finder:
    """Existence by an equi-join with ``key, hits`` of all n-grams up to the longest asked for."""
    found = lambda keys: keys.select("key").where(F.col("key") != "").distinct().join(grams.select("key", "hits"), "key")
    return Finder(found, lambda keys: found(keys).select("key"), longest)


@dataclass
class Prune:
    """Which prunings are on (the search by prefixes itself is ``iterative``)."""

    iterative: bool = True
    kgram: bool = False
    last_bits: bool = False
    cutoff: int = 50


@dataclass
class Edits:
    """Norms of tokens and the penalty constant; ``most`` bounds the edits of one
    pattern, by default as far as the threshold allows."""

    norms: DataFrame
    kappa: float
    kind: str = "both"
    most: int | None = None


def queries_of(df: DataFrame, id_col: str, tokens: str = "tokens", m: int | None = None) -> DataFrame:
    """``query_id, tokens, m``; with ``m`` the first tokens, where there are so many."""
    if m:
        df = df.where(F.size(tokens) >= m).withColumn(tokens, F.slice(tokens, 1, m))
    return df.select(F.col(id_col).alias("query_id"), F.col(tokens).alias("tokens"), F.size(tokens).alias("m")).where("m > 0")


def _pareto(rows: DataFrame) -> DataFrame:
    better = lambda x, y: (y.s <= x.s) & (y.lp >= x.lp) & (y.e <= x.e) & ((y.s < x.s) | (y.lp > x.lp) | (y.e < x.e))
    keep = F.filter("states", lambda x: ~F.exists("states", lambda y: better(x, y)))
    groups = rows.groupBy("query_id", "key").agg(F.first("tokens").alias("tokens"), F.first("m").alias("m"), F.collect_set(F.struct("s", "lp", "e")).alias("states"))
    return groups.withColumn("st", F.explode(keep)).select("query_id", "tokens", "m", "key", "st.s", "st.lp", "st.e")


def _extend(key, token):
    return F.when(key == "", token).otherwise(F.concat(key, F.lit(SEP), token))


def known_absent(cand: DataFrame, top: DataFrame, kgrams: DataFrame, k: int) -> DataFrame:
    """Candidates without those whose last ``k`` tokens are all frequent and not in the table."""
    t = F.split("key", SEP)
    rows = cand.withColumn("_tail", F.when(F.size(t) >= k, F.array_join(F.slice(t, -k, k), SEP)))
    for i in range(k):
        rows = rows.join(F.broadcast(top.select(F.col("token").alias(f"_w{i}"))), F.get(F.split("_tail", SEP), F.lit(i)) == F.col(f"_w{i}"), "left")
    rows = rows.join(F.broadcast(kgrams.select(F.col("key").alias("_g"))), F.col("_tail") == F.col("_g"), "left")
    frequent = F.col("_w0").isNotNull()
    for i in range(1, k):
        frequent = frequent & F.col(f"_w{i}").isNotNull()
    return rows.where(~(frequent & F.col("_g").isNull())).select(*cand.columns)


def soft_search(
    queries: DataFrame, theta: float, near: DataFrame, find: Finder, longest: int, edits: Edits | None = None, base: float = BASE,
    hard: bool = False, max_len: int | None = None, prune: Prune | None = None, kgrams: tuple[DataFrame, list[DataFrame]] | None = None,
    index: WindowIndex | None = None, expand: str = "lazy", edge_insertions: str = "include", trace: list | None = None,
) -> DataFrame:
    """``query_id, m, key, similarity, hits`` of all patterns at or above ``theta``.

    ``near`` is ``tok, nb, cos`` at or above ``theta``; ``longest`` the greatest query
    length; ``hard`` scores by the plain minimum (no edits).  Patterns hold at most
    ``max_len`` tokens (by default 8 more than the query), and no more than the finder can
    look up.  Steps ask only whether candidates occur; hits are counted once, for what is
    left at the end (with last-bits pruning, at each step).  With ``trace`` every step is
    written and its frames (candidates, those that occur) are appended.
    """
    if longest > find.longest:
        raise ValueError(f"queries of {longest} tokens exceed the {find.longest} that can be looked up")
    prune = prune or Prune()
    if prune.last_bits and (edits or index is None or hard):
        raise ValueError("last-bits pruning needs an index and equal lengths")
    near = near.select("tok", "nb", F.round("cos", 6).alias("cos"), cost(F.round("cos", 6), base).alias("a"))
    max_len = min(max_len or longest + 8, find.longest)
    if find.segments and not (edits or kgrams or prune.last_bits or trace is not None) and prune.iterative and max_len >= longest:
        cost_of = -F.col("cos") if hard else F.col("a")
        got = walk.grown(queries.where(F.col("m") <= longest), theta, near.select("tok", "nb", cost_of.alias("a")), find.segments, base, hard)
        score = F.round(-F.col("s"), 6) if hard else similarity(F.col("s"), F.lit(0.0), base)
        return got.select("query_id", "m", "key", score.alias("similarity"), "hits").where(F.col("similarity") >= theta)
    score = (lambda: F.round(-F.col("s"), 6)) if hard else (lambda: similarity(F.col("s"), F.col("lp"), base))
    add = (lambda: F.greatest(F.col("s"), -F.col("cos"))) if hard else (lambda: F.col("s") + F.col("a"))
    zero = -1.0 if hard else 0.0
    front = queries.select("query_id", "tokens", "m", F.lit("").alias("key"), F.lit(zero).alias("s"), F.lit(0.0).alias("lp"), F.lit(0).alias("e"))
    most = 0
    if edits:
        pen = edits.norms.select(F.col("token").alias("_t"), F.col("v").alias("_v"))
        low = edits.norms.agg(F.min("v")).first()[0] or 1.0
        most = edits.most if edits.most is not None else int(-longest * edits.kappa * math.log(theta) / low)
        # a loose list; each query's own length decides in the score
        can_insert = F.broadcast(pen.where(F.col("_v") <= -longest * edits.kappa * math.log(theta)))
    ins = bool(edits) and edits.kind in ("both", "ins")
    dele = bool(edits) and edits.kind in ("both", "del")

    def inserted(rows: DataFrame) -> DataFrame:
        out, last = rows, rows
        for _ in range(most if ins else 0):
            last = last.join(can_insert).select("query_id", "tokens", "m", _extend(F.col("key"), F.col("_t")).alias("key"), "s", (F.col("lp") - F.col("_v") / (F.col("m") * edits.kappa)).alias("lp"), (F.col("e") + 1).alias("e"))
            last = last.where((F.col("e") <= most) & (score() >= theta) & (key_size(F.col("key")) <= max_len))
            out = out.unionByName(last)
        return out

    def occurring(cand: DataFrame) -> DataFrame:
        if kgrams and prune.kgram:
            for k, table in zip((2, 3), kgrams[1], strict=False):
                cand = known_absent(cand, kgrams[0], table, k)
        cand = spool(cand, "candidates")
        found = find.hits(cand).select("key", F.col("hits").cast("long")) if prune.last_bits else find.occur(cand)
        kept = cand.join(spool(found, "found"), "key").select(*cand.columns, *["hits"] * prune.last_bits)
        if not dele:
            return kept
        empty = cand.where(F.col("key") == "")
        return kept.unionByName(empty.withColumn("hits", F.lit(0).cast("long")) if prune.last_bits else empty)

    done: list[DataFrame] = []
    columns = ["query_id", "tokens", "m", "key", "s", "lp", "e"]
    for i in range(1, longest + 1):
        act = front.where(F.col("m") >= i)
        q = F.element_at("tokens", i)
        sub = inserted(act).join(near, q == F.col("tok")).select("query_id", "tokens", "m", _extend(F.col("key"), F.col("nb")).alias("key"), add().alias("s"), "lp", "e")
        cand = sub
        if dele:
            gone = act.join(pen, q == F.col("_t")).select("query_id", "tokens", "m", "key", "s", (F.col("lp") - F.col("_v") / (F.col("m") * edits.kappa)).alias("lp"), (F.col("e") + 1).alias("e"))
            cand = cand.unionByName(gone.where(F.col("e") <= most))
        cand = cand.where((score() >= theta) & (key_size(F.col("key")) <= max_len))
        if ins and expand == "literal":
            cand = inserted(cand)
        if edits:
            cand = _pareto(cand)
        if not prune.iterative and i < longest:
            front = cand
            done.append(occurring(cand.where(F.col("m") == i)))
            continue
        if trace is not None:
            cand = spool(cand, "candidates")
        kept = occurring(cand)
        if trace is not None:
            kept = spool(kept, "occurring")
            trace.append((i, cand, kept))
        done.append(kept.where(F.col("m") == i))
        rest = kept.where(F.col("m") > i)
        if prune.last_bits and i < longest:
            rare = rest.where(F.col("hits") <= prune.cutoff)
            done.append(_finish_rare(rare, i, longest, near, index, theta, base))
            rest = rest.where(F.col("hits") > prune.cutoff)
        front = rest.select(*columns)
    ends = done[0]
    for d in done[1:]:
        ends = ends.unionByName(d)
    if ins and edge_insertions == "include":
        tail = inserted(ends.select(*columns)).join(ends.select("query_id", "key").distinct(), ["query_id", "key"], "left_anti")
        ends = ends.unionByName(occurring(_pareto(tail)))
    ends = ends.where(F.col("key") != "")
    if prune.last_bits:
        return ends.groupBy("query_id", "m", "key").agg(F.max(score()).alias("similarity"), F.max("hits").alias("hits"))
    best = spool(ends.groupBy("query_id", "m", "key").agg(F.max(score()).alias("similarity")), "ends")
    return best.join(find.hits(best), "key").select("query_id", "m", "key", "similarity", F.col("hits").cast("long"))


def _finish_rare(rare: DataFrame, i: int, longest: int, near: DataFrame, index: WindowIndex, theta: float, base: float) -> DataFrame:
    """Finish patterns of few occurrences on the index rows of their own range."""
    own = matching_windows(rare, index).join(rare, "key")
    t = F.split("window", SEP)
    own = own.where(F.size(t) >= F.col("m")).withColumn("w", F.slice(t, 1, F.col("m")))
    whole = own.groupBy("query_id", "tokens", "m", "key", "s", "lp", "e", "w").agg(F.sum("run").alias("hits"))
    slots = whole.select("*", F.explode(F.sequence(F.lit(i + 1), F.col("m"))).alias("j"))
    ok = slots.join(near, (F.element_at("tokens", F.col("j")) == F.col("tok")) & (F.element_at("w", F.col("j")) == F.col("nb")))
    full = ok.groupBy("query_id", "tokens", "m", "s", "lp", "e", "w", "hits").agg(F.count("*").alias("n"), F.sum("a").alias("more")).where(F.col("n") == F.col("m") - i)
    out = full.select("query_id", "tokens", "m", key_of(F.col("w")).alias("key"), (F.col("s") + F.col("more")).alias("s"), "lp", "e", "hits")
    return out.where(similarity(F.col("s"), F.col("lp"), base) >= theta)


def naive_search(queries: DataFrame, theta: float, near: DataFrame, find: Finder, longest: int, base: float = BASE, most: int = 50_000_000) -> DataFrame:
    """Enumerate every similar pattern, look them all up afterwards; refuses to explode."""
    size = queries.select("query_id", F.explode("tokens").alias("tok")).join(near.groupBy("tok").count(), "tok").groupBy("query_id").agg(F.exp(F.sum(F.log("count"))).alias("n")).agg(F.sum("n")).first()[0]
    if (size or 0) > most:
        raise ValueError(f"about {size:.3g} patterns; use soft_search")
    return soft_search(queries, theta, near, find, longest, base=base, prune=Prune(iterative=False))


def top_patterns(matches: DataFrame, n: int = 20) -> DataFrame:
    """The ``n`` best of each query: by similarity, hits, then pattern."""
    w = Window.partitionBy("query_id").orderBy(F.desc("similarity"), F.desc("hits"), "key")
    return matches.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= n)


def adaptive_search(queries: DataFrame, search: Callable[[DataFrame, float], DataFrame], n_wanted: int = 20, start: float = 0.85, step: float = 0.1, floor: float = 0.45, strategy: str = "stepwise", steps: list[float] | None = None) -> DataFrame:
    """Top patterns with the threshold relaxed until each query has enough.

    ``stepwise`` searches again for unfinished queries only; ``floor`` searches once
    at the floor and takes the best: the same answer.  Adds ``theta``, the last one used.
    """
    levels = steps or [round(start - k * step, 6) for k in range(int((start - floor) / step + 1e-9) + 1)]
    if levels[-1] > floor:
        levels = [*levels, floor]
    if strategy == "floor":
        found = spool(search(queries, floor), "floor")
        best = top_patterns(found, n_wanted)
        enough = found.groupBy("query_id").agg(*[F.count_if(F.col("similarity") >= t).alias(f"c{k}") for k, t in enumerate(levels)])
        used = F.coalesce(*[F.when(F.col(f"c{k}") >= n_wanted, F.lit(t)) for k, t in enumerate(levels)], F.lit(floor))
        return best.join(enough.select("query_id", used.alias("theta")), "query_id")
    todo, out = queries, None
    for k, t in enumerate(levels):
        found = spool(search(todo, t), "level")
        full = found.groupBy("query_id").count().where(F.col("count") >= n_wanted).select("query_id")
        last = k == len(levels) - 1
        ready = (found if last else found.join(full, "query_id", "left_semi")).withColumn("theta", F.lit(t))
        out = ready if out is None else out.unionByName(ready)
        if last:
            break
        todo = todo.join(full, "query_id", "left_anti")
        if todo.isEmpty():
            break
    return top_patterns(out, n_wanted)


