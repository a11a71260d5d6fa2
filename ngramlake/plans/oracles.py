"""DuckDB counterparts of the registered workloads, each tokenizing for itself."""

from __future__ import annotations

TOKEN = r"[\p{L}\p{N}]+|[^\s\p{L}\p{N}\x00-\x1f]"
DIM = 64
LN = "ln(1e4)"


def _toks(col: str = "text") -> str:
    return f"regexp_extract_all(lower({col}), '{TOKEN}')"


C = f"c as (select doc_id, lang, coalesce({_toks()}, []) as t from documents)"
B = f"b as (select item_id, coalesce({_toks()}, []) as t from benchmark)"
V = "v as (select token, count(*) as freq, -ln(count(*) / (select sum(len(t)) from c)) as v from (select unnest(t) as token from c) group by 1)"
K = "k as (select max(v) / 5 as kappa from (select v from v order by v, token limit 50))"


def asked(m: int) -> str:
    return f"q as (select item_id as query_id, t[1:{m}] as qt from b where len(t) >= {m})"


def grams(n: int, source: str = "c", name: str = "") -> str:
    cols = ", ".join(f"t[i + {k}] as t{k + 1}" for k in range(n))
    return f"{name or f'g{n}'} as (select {cols}, count(*) as hits from (select t, unnest(range(1, len(t) - {n} + 2)) as i from {source}) group by all)"


def key(n: int, alias: str = "") -> str:
    return " || ' ' || ".join(f"{alias}t{k}" for k in range(1, n + 1))


def near(words: str, theta: float, vocabulary: str = "select token from v", z: str = "") -> str:
    """``n(tok, nb, cos)``: neighbours of the tokens of a subquery ``words(token)``;
    ``z`` goes before the names."""
    sums = ", ".join(f"sum(ev[{d}]) as d{d}" for d in range(1, DIM + 1))
    dims = ", ".join(f"d{d}" for d in range(1, DIM + 1))
    return f"""
{z}e as (select vec_id, embedding::DOUBLE[] as ev from embeddings),
{z}nn as (select count(*) as nn from embeddings),
{z}words as (select distinct token from ({words})),
{z}gr as (select token, unnest(list_concat(flatten(list_transform([3, 4, 5], lambda n: list_transform(range(1, greatest(length(s) - n + 2, 1)), lambda i: substr(s, i, n)))), [s])) as g
       from (select token, '<' || token || '>' as s from ({vocabulary} union select token from {z}words))),
{z}gb as (select token, ('0x' || substr(md5(g), 1, 8))::BIGINT % nn as bucket from {z}gr, {z}nn),
{z}gv as (select token, [{dims}] as x from (select token, {sums} from {z}gb join {z}e on vec_id = bucket group by token)),
{z}gu as (select token, list_transform(x, lambda y: y / sqrt(list_inner_product(x, x))) as u from {z}gv),
{z}num as (select ev as ne from {z}e where vec_id = (select ('0x' || substr(md5('#num'), 1, 8))::BIGINT % nn from {z}nn)),
{z}gn as (select token, case when regexp_full_match(token, '[0-9]+') then list_transform(u, lambda y, i: y + 2 * ne[i]) else u end as x from {z}gu, {z}num),
{z}lex as (select token, list_transform(x, lambda y: y / sqrt(list_inner_product(x, x))) as u from {z}gn),
{z}n as (select w.token as tok, l.token as nb, round(list_inner_product(w.u, l.u), 6) as cos
      from (select x.* from {z}lex x join {z}words using (token)) w, (select x.* from {z}lex x join ({vocabulary}) using (token)) l where round(list_inner_product(w.u, l.u), 6) >= {theta})"""


def cost(cs: list[str]) -> str:
    return " + ".join(f"pow(1e4, 1 - {c}) - 1" for c in cs)


def smooth(cs: list[str]) -> str:
    return f"greatest(0, 1 - ln(1 + {cost(cs)}) / {LN})"


def matches(m: int, theta: float, hard: bool = False, insert: int = 0, delete: int = 0) -> str:
    """Patterns of one shape: no edit, or one insertion or deletion at a place."""
    length = m + bool(insert) - bool(delete)
    slots = [i for i in range(1, m + 1) if i != delete]
    places = [k for k in range(1, length + 1) if k != insert]
    joins, cs = [], []
    for j, (i, k) in enumerate(zip(slots, places, strict=True)):
        joins.append(f"join n n{i} on n{i}.tok = q.qt[{i}]" + ("" if j == 0 else f" and n{i}.nb = g.t{k}"))
        if j == 0:
            joins.append(f"join g{length} g on g.t{k} = n{i}.nb")
        cs.append(f"n{i}.cos")
    score = f"least({', '.join(cs)})" if hard else smooth(cs)
    if insert:
        joins.append(f"join v on v.token = g.t{insert}")
    if delete:
        joins.append(f"join v on v.token = q.qt[{delete}]")
    if insert or delete:
        score = f"{score} * exp(-v.v / ({m} * (select kappa from k)))"
    return f"select query_id, {key(length, 'g.')} as pattern, round({score}, 6) as similarity, g.hits as hits from q {' '.join(joins)} where round({score}, 6) >= {theta}"


def soft(m: int, theta: float, hard: bool = False, edits: str = "none") -> str:
    shapes = [matches(m, theta, hard)]
    sizes = [m]
    if edits == "ins":
        shapes += [matches(m, theta, insert=j) for j in range(1, m + 2)]
        sizes.append(m + 1)
    if edits == "del":
        shapes += [matches(m, theta, delete=j) for j in range(1, m + 1)]
        sizes.append(m - 1)
    parts = [C, B, V, K, asked(m), *[grams(n) for n in sizes], near("select unnest(qt) as token from q", theta)]
    return f"with {', '.join(parts)} select query_id, pattern, max(similarity) as similarity, max(hits)::BIGINT as hits from ({' union all '.join(shapes)}) group by 1, 2"


def chain(m: int, theta: float) -> str:
    """CTEs ``p1, c1, .. pm, cm``: candidates and kept patterns of each step, from ``q``."""
    out = ["p0 as (select query_id, qt, 0.0::DOUBLE as s from q)", "c0 as (select * from p0)"]
    for i in range(1, m + 1):
        before = ", ".join(f"c{i - 1}.t{k}" for k in range(1, i))
        s = f"c{i - 1}.s + pow(1e4, 1 - n.cos) - 1"
        names = ", ".join(f"t{k}" for k in range(1, i + 1))
        out.append(f"p{i} as (select query_id, qt, {before + ', ' if before else ''}n.nb as t{i}, {s} as s from c{i - 1} join n on n.tok = qt[{i}] where round(greatest(0, 1 - ln(1 + {s}) / {LN}), 6) >= {theta})")
        out.append(f"c{i} as (select p{i}.* from p{i} join (select {names}, hits from g{i}) using ({names}))")
    return ", ".join(out)


def _steps(m: int, theta: float) -> str:
    head = [C, B, V, asked(m), *[grams(n) for n in range(1, m + 1)], near("select unnest(qt) as token from q", theta), chain(m, theta)]
    rows = " union all ".join(f"select {i} as step, (select count(*) from p{i}) as candidates, (select count(*) from c{i}) as kept" for i in range(1, m + 1))
    return f"with {', '.join(head)}, steps as ({rows})"


def _hits(longest: int) -> str:
    heads = f"p as (select distinct n, array_to_string(t[1:n], ' ') as pattern from (select t, unnest(range(1, least(len(t), {longest}) + 1)) as n from b))"
    every = " union all ".join(f"select {n} as n, array_to_string(t[i:i + {n - 1}], ' ') as pattern from (select t, unnest(range(1, len(t) - {n} + 2)) as i from c)" for n in range(1, longest + 1))
    return f"with {C}, {B}, {heads}, g as (select pattern, count(*) as hits from ({every}) where pattern in (select pattern from p) group by 1), h as (select n, pattern, coalesce(hits, 0) as hits from p left join g using (pattern))"


W10 = "w as (select array_to_string(t[i:i + 9], chr(1)) as key, count(*) as run from (select t, unnest(range(1, len(t) + 1)) as i from c) group by 1), r as (select *, row_number() over (order by key) - 1 as rank from w)"
FENCE = "f as (select rank // 4096 as block, min(key) as first_key, count(*) as entries, sum(run)::BIGINT as n from r group by 1)"


def _bm25(m: int, k: int) -> str:
    return f"""with {C}, {B}, {asked(m)}, st as (select count(*) as n, avg(len(t)) as avgdl from c),
terms as (select distinct query_id, unnest(qt) as token from q),
tf as (select doc_id, len(any_value(t)) as dl, token, count(*) as tf from (select doc_id, t, unnest(t) as token from c) where token in (select token from terms) group by doc_id, token),
df as (select token, count(*) as df from tf group by 1),
w as (select token, doc_id, ln(1 + (n - df + 0.5) / (df + 0.5)) * tf * 2.2 / (tf + 1.2 * (0.25 + 0.75 * dl / avgdl)) as w from tf join df using (token), st),
s as (select query_id, doc_id, round(sum(w), 6) as score from terms join w using (token) group by 1, 2),
ranked as (select *, row_number() over (partition by query_id order by score desc, doc_id) as rank from s qualify rank <= {k})"""


HELD = "held as (select item_id as query_id, doc_id from documents d join benchmark b on contains(d.text, b.text))"


def _top(m: int) -> str:
    inner = soft(m, 0.45)
    return f"select query_id, rank, pattern, similarity, hits from (select *, row_number() over (partition by query_id order by similarity desc, hits desc, replace(pattern, ' ', chr(1))) as rank from ({inner})) where rank <= 20"


def _contam(items: str, search: bool) -> str:
    """η of windows of ``x(item_id, t)``."""
    windows = "w as (select item_id, t[i:i + 9] as qt, array_to_string(t[i:i + 9], chr(1)) as key from (select item_id, t, unnest(range(1, greatest(len(t) - 9, 1) + 1)) as i from x))"
    exact = "ex as (select distinct array_to_string(t[i:i + 9], chr(1)) as key from (select t, unnest(range(1, len(t) - 8)) as i from c))"
    parts = [C, B, V, items, windows, exact]
    hit = "select key from ex"
    if search:
        parts += ["q as (select distinct key as query_id, qt from w where key not in (select key from ex))", *[grams(n) for n in range(1, 11)], near("select unnest(qt) as token from w", 0.6), chain(10, 0.6)]
        hit += " union select query_id from c10"
    return f"with {', '.join(parts)}, hit as ({hit}), eta as (select item_id, count(*) as windows, round(avg((h.key is not null)::INT), 6) as eta from w left join (select distinct key from hit) h using (key) group by 1)"


def _planted() -> str:
    """Items with the 15th token swapped for its nearest other word."""
    lex = near("select t[15] as token from b where len(t) >= 15", 0.6, z="z")
    best = "best as (select tok, nb from (select tok, nb, row_number() over (partition by tok order by cos desc, nb) as r from zn where tok <> nb) where r = 1)"
    x = "x as (select item_id, case when nb is null then t else list_concat(t[1:14], [nb], t[16:]) end as t from b left join best on t[15] = tok)"
    return f"{lex}, {best}, {x}"


PAIRS = f"""with {C}, g as (select distinct doc_id, array_to_string(t[i:i + 4], chr(1)) as key from (select doc_id, t, unnest(range(1, len(t) - 3)) as i from c)),
d as (select key from g group by 1 having count(*) >= 2),
s as (select doc_id, count(*) as n from g group by 1),
ab as (select distinct x.doc_id as a, y.doc_id as b from g x join d using (key) join g y using (key) where x.doc_id < y.doc_id),
j as (select a, b, count(*) as c from ab join g x on x.doc_id = a join g y on y.doc_id = b and x.key = y.key group by 1, 2),
p as (select a, b, round(c / (sa.n + sb.n - c), 6) as jaccard, round((c / sa.n + c / sb.n) / 2, 6) as score from j join s sa on sa.doc_id = a join s sb on sb.doc_id = b),
pairs as (select *, (jaccard >= 0.5)::INT as label from p)"""

HTML = r"""trim(regexp_replace(replace(replace(replace(replace(replace(replace(
 regexp_replace(regexp_replace(regexp_replace(html, '(?is)<(script|style)\b.*?</(script|style)>', ' ', 'g'), '(?s)<!--.*?-->', ' ', 'g'), '(?s)<[^>]*>', ' ', 'g'),
 '&nbsp;', ' '), '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&#39;', ''''), '&amp;', '&'), '\s+', ' ', 'g'))"""


def build() -> dict[str, str]:
    o: dict[str, str] = {}
    o["vocab_top"] = f"with {C} select row_number() over (order by freq desc, token) - 1 as token_id, token, freq, round(freq / (select sum(len(t)) from c), 9) as p from (select token, count(*) as freq from (select unnest(t) as token from c) group by 1) qualify token_id < 100"
    o["token_stats_by_lang"] = f"with {C} select lang, count(distinct doc_id) as docs, sum(len(t))::BIGINT as tokens, (select count(distinct u) from (select unnest(t) as u from c c2 where c2.lang is not distinct from c.lang)) as types from c group by lang"
    o["windows_count"] = f"with {C}, {W10} select sum(run)::BIGINT as windows, count(*) as distinct_windows from w"
    o["swa_fences"] = f"with {C}, {W10}, {FENCE} select block, replace(first_key, chr(1), ' ') as first_key, entries, n, coalesce(sum(n) over (order by block rows between unbounded preceding and 1 preceding), 0)::BIGINT as before from f"
    o["swa_prefix_bytes"] = f"""with {C}, {W10}, x as (select rank // 4096 as block, key, coalesce(lag(key) over (partition by rank // 4096 order by rank), '') as prev from r),
y as (select block, key, coalesce(list_sum(list_transform(range(1, least(length(key), length(prev)) + 1), lambda i: (substr(key, 1, i) = substr(prev, 1, i))::INT)), 0) as same from x)
select block, sum(length(key))::BIGINT as plain, sum(length(key) - same)::BIGINT as coded from y group by 1"""
    o["index_sizes"] = f"""with {C}, {W10}, x as (select rank // 4096 as block, encode(key) as key, run, coalesce(lag(encode(key)) over (partition by rank // 4096 order by rank), ''::BLOB) as prev from r),
y as (select run, octet_length(key) as size, hex(key) as key, hex(prev) as prev from x),
z as (select run, size, coalesce(list_sum(list_transform(range(1, least(length(key), length(prev)) // 2 + 1), lambda i: (substr(key, 1, 2 * i) = substr(prev, 1, 2 * i))::INT)), 0) as same from y)
select sum(size * run)::BIGINT as plain, sum(size + 8)::BIGINT as counted, count(*) as keys, sum(size - same + 16)::BIGINT as coded, (select sum(octet_length(encode(text))) from documents)::BIGINT as text from z"""
    o["swa_runs"] = f"with {C}, {W10} select run, count(*) as windows from w group by 1"
    for name in ("exact_hits", "exact_hits_sql"):
        o[name] = f"{_hits(10)} select pattern, hits from h"
    o["exact_exists"] = f"{_hits(10)} select n, count(*) as patterns, count(*) filter (hits > 0) as found from h group by 1"
    for name in ("sa_lookup", "fm_lookup", "scan_windows"):
        o[name] = f"{_hits(5)} select pattern, hits from h"
    o["exact_occurrences"] = f"with {C}, {B}, p as (select distinct array_to_string(t[1:5], ' ') as pattern from b where len(t) >= 5) select pattern, doc_id, (i - 1)::INT as pos from (select doc_id, i, array_to_string(t[i:i + 4], ' ') as pattern from (select doc_id, t, unnest(range(1, len(t) - 3)) as i from c)) join p using (pattern)"
    o["exact_long"] = f"with {C}, {B}, p as (select distinct array_to_string(t[1:15], ' ') as pattern from b where len(t) >= 15), g as (select array_to_string(t[i:i + 14], ' ') as pattern, count(*) as hits from (select t, unnest(range(1, len(t) - 13)) as i from c) group by 1) select pattern, coalesce(hits, 0) as hits from p left join g using (pattern)"
    top = "top as (select token from v order by freq desc, token limit 50)"
    o["kgram_table"] = f"with {C}, {V}, {top}, {grams(2)}, {grams(3)} select 2 as k, t1 || ' ' || t2 as gram from g2 where t1 in (from top) and t2 in (from top) union all select 3, t1 || ' ' || t2 || ' ' || t3 from g3 where t1 in (from top) and t2 in (from top) and t3 in (from top)"
    o["ngram_distinct"] = f"with {C}, {', '.join(grams(n) for n in range(1, 6))} " + " union all ".join(f"select {n} as n, count(*) as types from g{n}" for n in range(1, 6))
    o["neighbors"] = f"with {C}, {B}, {V}, {asked(5)}, {near('select unnest(qt) as token from q', 0.45)} select tok, nb, cos from n"
    o["surprisal_norm"] = f"with {C}, {V} select token, round(v, 6) as v from v"
    o["penalty_constant"] = f"with {C}, {V}, {K} select round(kappa, 6) as kappa, round(exp(-1), 6) as factor from k"
    for name in ("soft_sub", "soft_sub_last_bits", "soft_sub_kgram"):
        o[name] = soft(5, 0.6)
    o["soft_sub_hardmin"] = soft(5, 0.6, hard=True)
    o["soft_ins1"] = soft(5, 0.6, edits="ins")
    o["soft_del1"] = soft(5, 0.6, edits="del")
    o["naive_soft"] = soft(2, 0.6)
    o["predecessor_soft"] = soft(3, 0.6, hard=True)
    o["soft_topn"] = o["adaptive_topn"] = _top(3)
    o["short_answers"] = f"with m as ({soft(3, 0.45)}), n as (select item_id as query_id, count(m.query_id) as c from benchmark left join m on m.query_id = item_id where len({_toks()}) >= 3 group by 1) select count(*) as queries, count(*) filter (c < 20) as short, round(count(*) filter (c < 20) / count(*), 6) as share from n"
    o["method_ticks"] = f"with s as ({soft(3, 0.6)}), h as ({soft(3, 0.6, hard=True)}) select s.query_id, row_number() over (partition by s.query_id order by s.similarity desc, s.hits desc, replace(s.pattern, ' ', chr(1))) as rank, s.pattern, s.similarity, s.hits, h.pattern is not null as in_predecessor, s.similarity = 1 as in_exact from s left join h using (query_id, pattern) qualify rank <= 20"
    o["lookups_count"] = f"{_steps(5, 0.6)} select * from steps"
    per = " union all ".join(f"select query_id, count(*) as n from p{i} group by 1" for i in range(1, 6))
    o["lookups_geomean"] = f"{_steps(5, 0.6)}, per as (select query_id, sum(n) as t from ({per}) group by 1) select round(exp(avg(ln(t))), 6) as geo_mean, max(t)::BIGINT as most, sum(t)::BIGINT as total from per"
    o["growth_bound"] = f"""{_steps(5, 0.6)}, x as (select step, candidates / (select count(*) from q) as p, kept / (select count(*) from q) as c from steps),
y as (select *, coalesce(lag(c) over (order by step), 1.0) as before from x),
z as (select max(case when before > 0 then p / before end) as a, exp(regr_slope(case when c > 0 then ln(c) end, step)) as r, sum(p) as lookups from y),
kk as (select a, r, lookups, greatest(1.0, max(case when c > 0 then c / pow(r, step) end)) as k from y, z group by all)
select round(a, 6) as a, round(k, 6) as k, round(r, 6) as r, round(lookups, 6) as lookups, round(a * k * (1 - pow(r, 5)) / (1 - r), 6) as bound from kk"""
    sums = " union all ".join(f"select 'iterative' as pruning, query_id, {m} as m, sum(n)::DOUBLE as lookups from ({' union all '.join(f'select query_id, count(*) as n from p{i} group by 1' for i in range(1, m + 1))}) group by query_id" for m in range(1, 6))
    o["ablation_growth"] = f"""{_steps(5, 0.6)}, nn2 as (select tok, count(*) as n from n group by 1), sl as (select query_id, i, n from (select query_id, qt, unnest(range(1, 6)) as i from q) join nn2 on tok = qt[i]),
every as (select 'none' as pruning, query_id, i as m, exp(sum(ln(n)) over (partition by query_id order by i)) as lookups from sl),
t as (select pruning, m, avg(ln(lookups)) as t from ({sums} union all from every) group by 1, 2)
select pruning, round(exp(regr_slope(t, m)), 6) as factor from t group by 1"""
    o["threshold_sweep"] = f"with m as ({soft(3, 0.45)}), q as (select item_id as query_id from benchmark where len({_toks()}) >= 3) " + " union all ".join(f"select {t}::DOUBLE as theta, coalesce(sum(c), 0)::BIGINT as patterns, count(*) filter (c >= 1) as n1, count(*) filter (c >= 5) as n5, count(*) filter (c >= 20) as n20 from (select q.query_id, count(m.query_id) as c from q left join m on m.query_id = q.query_id and similarity >= {t} group by 1)" for t in (0.45, 0.5, 0.55, 0.6, 0.7, 0.8))
    o["base_sweep"] = " union all ".join(f"select {b} as base, count(*) as patterns, round(avg(similarity), 5) as mean from ({soft(3, 0.6).replace('1e4', f'{b}.0')})" for b in (10, 100, 10000, 1000000))
    o["judge_winrate"] = f"with s as (select query_id, count(*) as x from ({soft(3, 0.6)}) group by 1), h as (select query_id, count(*) as y from ({soft(3, 0.6, hard=True)}) group by 1), v as (select coalesce(x, 0) as x, coalesce(y, 0) as y from (select item_id as query_id from benchmark where len({_toks()}) >= 3) left join s using (query_id) left join h using (query_id)) select 'soft' as a, 'predecessor' as b, sum(case when x > y then 1.0 when x < y then 0.0 else 0.5 end)::DOUBLE as wins, round(avg(case when x > y then 1.0 when x < y then 0.0 else 0.5 end), 6) as share from v"
    cw = lambda t, i: f"select {i}, unnest(list_transform(range(1, greatest(length(text) - 49, 1) + 1), lambda k: substr(text, k, 50))) as key from {t} where length(text) > 0"
    o["contam_characters"] = f"with w as ({cw('benchmark', 'item_id')}), h as (select distinct key from ({cw('documents', 'doc_id')}) where key in (select key from w)) select item_id, count(*) as windows, round(avg((h.key is not null)::INT), 6) as eta, round(avg((h.key is not null)::INT), 6) >= 0.8 as dirty from w left join h using (key) group by 1"
    o["zipf_fit"] = f"with {C}, {V}, r as (select freq, row_number() over (order by freq desc, token) as rank from v qualify rank <= 2000) select round(-regr_slope(ln(freq), ln(rank)), 6) as alpha, round(regr_r2(ln(freq), ln(rank)), 6) as r2 from r"
    o["heaps_fit"] = f"""with {C}, s as (select doc_id, ntile(20) over (order by doc_id) as step from c), x as (select step, unnest(t) as token from c join s using (doc_id)),
f as (select token, min(step) as step from x group by 1), n as (select step, count(*) as n from x group by 1), w as (select step, count(*) as w from f group by 1),
p as (select step, sum(n) over (order by step) as tokens, sum(coalesce(w, 0)) over (order by step) as types from n left join w using (step))
select round(regr_slope(ln(types), ln(tokens)), 6) as exponent, round(regr_r2(ln(types), ln(tokens)), 6) as r2 from p"""
    o["latency_p95"] = "select event_type as method, count(*) as runs, count(*) filter (event_type = 'error') as failed, round(quantile_cont(case when event_type <> 'error' then value end, 0.5), 6) as p50, round(quantile_cont(case when event_type <> 'error' then value end, 0.95), 6) as p95 from events group by 1"
    o["contam_exact"] = f"{_contam('x as (select item_id, t from b)', False)} select item_id, windows, eta, eta >= 0.8 as dirty from eta"
    o["contam_soft"] = f"{_contam(_planted(), True)} select item_id, windows, eta, eta >= 0.8 as dirty from eta"
    o["contam_extra"] = f"{_contam(_planted(), True)}, eta2 as (select item_id, round(avg((h.key is not null)::INT), 6) as eta from w left join ex h using (key) group by 1) select item_id, windows, eta from eta where eta >= 0.8 and item_id not in (select item_id from eta2 where eta >= 0.8)"
    o["contam_report"] = f"""{_contam(_planted(), True)}, eta2 as (select item_id, round(avg((h.key is not null)::INT), 6) as eta from w left join ex h using (key) group by 1), {HELD},
f as (select item_id, eta.eta >= 0.8 as soft, eta2.eta >= 0.8 as exact, item_id in (select query_id from held) as truth from eta join eta2 using (item_id))
select truth, count(*) as items, sum(exact::INT)::BIGINT as exact, sum((soft and not exact)::INT)::BIGINT as extra from f group by rollup (truth)"""
    o["scan_contains"] = f"with {HELD} select query_id as item_id, doc_id from held"
    o["scan_regex"] = "select doc_id, len(regexp_extract_all(text, '[a-zA-Z0-9._]+@[a-zA-Z0-9.]+'))::INT as n from documents where regexp_matches(text, '[a-zA-Z0-9._]+@[a-zA-Z0-9.]+')"
    o["scan_lev"] = "with n as (select distinct p_name from part) select x.p_name, y.p_name as other, levenshtein(x.p_name, y.p_name)::INT as distance from n x join n y on x.p_name < y.p_name and abs(length(x.p_name) - length(y.p_name)) <= 3 where levenshtein(x.p_name, y.p_name) <= 3"
    o["bm25"] = f"{_bm25(5, 10)} select query_id, doc_id, score, rank from ranked"
    o["tfidf"] = f"""with {C}, {B}, {asked(5)}, terms as (select distinct query_id, unnest(qt) as token from q),
tf as (select doc_id, token, count(*) as tf from (select doc_id, unnest(t) as token from c) where token in (select token from terms) group by 1, 2),
df as (select token, count(*) as df from tf group by 1),
s as (select query_id, doc_id, round(sum((1 + ln(tf)) * ln((select count(*) from c) / df)), 6) as score from terms join tf using (token) join df using (token) group by 1, 2)
select query_id, doc_id, score, row_number() over (partition by query_id order by score desc, doc_id) as rank from s qualify rank <= 10"""
    o["dense_topk"] = "with v as (select vec_id, embedding::DOUBLE[] as ev from embeddings), s as (select q.vec_id as query_id, r.vec_id, round(list_cosine_similarity(q.ev, r.ev), 6) as score from v q join v r on q.vec_id <> r.vec_id where q.vec_id % 100 = 0) select query_id, vec_id, score, row_number() over (partition by query_id order by score desc, vec_id) as rank from s qualify rank <= 10"
    ranked = f"{_bm25(10, 1000)}, {HELD}, h as (select query_id, rank from ranked join held using (query_id, doc_id)), n as (select query_id, count(*) as n from held group by 1)"
    at = lambda k: f"(select count(*) from h where h.query_id = n.query_id and rank <= {k})"
    o["ir_p_at_k"] = f"{ranked} select query_id, round({at(1)} / 1, 6) as p1, round({at(20)} / 20, 6) as p20 from n"
    o["ir_r_at_k"] = f"{ranked} select query_id, round({at(5)} / n, 6) as r5, round({at(1000)} / n, 6) as r1000 from n"
    o["paraphrase"] = f"{PAIRS} select a, b, jaccard, score, label from pairs"
    o["paraphrase_metrics"] = f"""{PAIRS}, t as (select score, sum(label) as pos, sum(1 - label) as neg from pairs group by 1),
u as (select *, coalesce(sum(neg) over (order by score rows between unbounded preceding and 1 preceding), 0) as below from t),
auc as (select round(sum(pos * (below + neg / 2)) / (sum(pos) * sum(neg)), 6) as auc from u)
select count(*) as pairs, round(avg(((score >= 0.6)::INT = label)::INT), 6) as accuracy,
round(2 * count(*) filter (score >= 0.6 and label = 1) / (2 * count(*) filter (score >= 0.6 and label = 1) + count(*) filter (score >= 0.6 and label = 0) + count(*) filter (score < 0.6 and label = 1)), 6) as f1, (select auc from auc) as auc from pairs"""
    o["pages_text"] = f"select page_id, length(x)::INT as chars, len({_toks('x')})::INT as tokens from (select page_id, {HTML} as x from pages)"
    o["conv_queries"] = f"select conv_id, turn, array_to_string(t[1:10], ' ') as query, least(len(t), 10)::INT as m from (select conv_id, turn, {_toks()} as t from conversations where role = 'user') where len(t) > 0"
    o["tokenizer_modes"] = f"select sum(len({_toks()}))::BIGINT as word, sum(len(regexp_extract_all(text, '{TOKEN}')))::BIGINT as word_cased, sum(len(regexp_extract_all(text, '\\S+')))::BIGINT as whitespace, sum(len(regexp_extract_all(text, '\\S')))::BIGINT as \"char\", sum(list_sum(list_transform({_toks()}, lambda w: ceil(length(w) / 4.0)))::BIGINT)::BIGINT as piece from documents"
    return o
