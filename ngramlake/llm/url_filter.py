"""URL filter: host reputation by empirical Bayes, with fixed rules above it.

A page's labelled outcome is good or bad.  Outcomes are counted for each host,
registered domain (last two labels) and suffix (last label).  The rate of bad
pages is shrunk downwards: the overall rate is the prior of a suffix, a suffix's
posterior mean the prior of its domains, a domain's that of its hosts.  The
weight of each prior (in pages) comes from the moments of the level below it: the
spread of its rates beyond what binomial draws would show.  A page is blocked if the
lower ``TAIL`` quantile of its host's beta posterior lies above the overall rate times
``margin``: the host is worse than the corpus beyond chance.  A host without
labels has its prior alone: the posterior mean of its domain, else of its suffix,
else the overall rate, with the weight of a host's prior.

All of it is DataFrame code; hosts are counted with partial aggregation, so a
hot host is one row per task, and the join back to the pages can be split.  The table
of hosts is written once; of each level only the overall rate and three weights, four
numbers, come to the driver.

Cases: null url or one without ``://`` has empty host and path, and is judged as
the host ``''``; a null label counts for nothing; an empty label table gives the
prior rate 0 and allows; of rules of equal length that fit, the one later in order of
host, path and verdict wins; pages are returned once for each input row, even when
labels repeat (labels are averaged for each page first); further columns are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import spool

#: host, path, verdict: fixed values of the contract.
RULES = (("net", "/", "block"), ("example.net", "/en/", "allow"), ("example.com", "/de/", "block"), ("org", "/fr/", "allow"))
#: Lower tail of the posterior and its normal quantile; factor on the overall rate.
TAIL, Z, MARGIN = 0.05, -1.6448536269514722, 1.0
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
PARTS = r"(?s)\A.*?://([^/?#]*)([^?#]*)"


def host_of(url: Column) -> Column:
    return F.translate(F.coalesce(F.regexp_extract(url, PARTS, 1), F.lit("")), UPPER, LOWER)


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, PARTS, 2), F.lit(""))


def domain_of(host: Column) -> Column:
    return F.substring_index(host, ".", -2)


def suffix_of(host: Column) -> Column:
    return F.substring_index(host, ".", -1)


def rule_of(host: Column, path: Column, rules=RULES) -> tuple[Column, Column]:
    """The longest rule that fits and its verdict; null where none does."""
    name, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for h, p, v in sorted(rules, key=lambda r: (len(r[0] + r[1]), r)):
        fits = ((host == h) | host.endswith(f".{h}")) & path.startswith(p)
        name, verdict = F.when(fits, F.lit(h + p)).otherwise(name), F.when(fits, F.lit(v)).otherwise(verdict)
    return name, verdict


def _prior_weight(level: DataFrame, rate: str) -> Column:
    """Aggregate: pages that the prior counts for, by moments of the level's rates."""
    p, n = F.col(rate), F.col("n").cast("double")
    within = F.sum(n * p * (1 - p))
    # weighted squares of observed minus expected rate; binomial part removed
    over = F.sum(n * F.pow(F.col("bad") / n - p, 2)) - F.sum(p * (1 - p))
    return F.when(over > 1e-9, F.least(F.greatest(within / over - 1, F.lit(1.0)), F.lit(1e4))).otherwise(F.lit(1e4))


def beta_tail(a: Column, b: Column, z: float = Z) -> Column:
    """Quantile of a beta distribution at the normal quantile ``z`` (a closed form by a
    normal transform, for ``a`` above a half; 0 below, where the mass lies near 0)."""
    p, q = 1 / (2 * a - 1), 1 / F.greatest(2 * b - 1, F.lit(0.05))
    h, c = 2 / (p + q), (z * z - 3) / 6
    w = -z * F.sqrt(F.greatest(h + c, F.lit(0.0))) / h - (q - p) * (c + 5 / 6 - 2 / (3 * h))
    return F.when(a > 0.5, a / (a + b * F.exp(2 * w))).otherwise(0.0)


def reputation(labelled: DataFrame, every: DataFrame | None = None) -> tuple[DataFrame, float]:
    """``host, n, bad, mean, bound`` from rows ``host, bad`` (bad in 0..1), and the overall rate.

    With ``every``, distinct rows ``host``: for those hosts, labelled or not."""
    hosts = labelled.groupBy("host").agg(F.count("*").alias("n"), F.sum("bad").alias("bad"))
    hosts = spool(hosts.withColumn("domain", domain_of(F.col("host"))).withColumn("suffix", suffix_of(F.col("host"))), "hosts")
    posterior = lambda rate, w: (F.col("bad") + w * F.col(rate)) / (F.col("n") + w)
    weight = lambda level, rate: level.agg(_prior_weight(level, rate)).first()[0] or 1.0
    whole = hosts.agg(F.sum("bad") / F.sum("n")).first()[0] or 0.0
    suffixes = hosts.groupBy("suffix").agg(F.sum("n").alias("n"), F.sum("bad").alias("bad")).withColumn("rate0", F.lit(whole))
    suffixes = spool(suffixes.select("suffix", posterior("rate0", weight(suffixes, "rate0")).alias("rate1")), "suffixes")
    domains = hosts.groupBy("domain", "suffix").agg(F.sum("n").alias("n"), F.sum("bad").alias("bad")).join(suffixes, "suffix")
    domains = spool(domains.select("domain", posterior("rate1", weight(domains, "rate1")).alias("rate2")), "domains")
    own = hosts.join(domains, "domain")
    w = weight(own, "rate2")
    if every is not None:
        own = every.select("host", domain_of(F.col("host")).alias("domain"), suffix_of(F.col("host")).alias("suffix"))
        own = own.join(hosts.select("host", "n", "bad"), "host", "left").join(domains, "domain", "left").join(suffixes, "suffix", "left")
        own = own.select("host", F.coalesce("n", F.lit(0)).alias("n"), F.coalesce("bad", F.lit(0.0)).alias("bad"), F.coalesce("rate2", "rate1", F.lit(whole)).alias("rate2"))
    a, b = F.col("bad") + w * F.col("rate2"), F.col("n") - F.col("bad") + w * (1 - F.col("rate2"))
    return own.select("host", "n", "bad", (a / (a + b)).alias("mean"), beta_tail(a, b).alias("bound")), whole


def judge(
    pages: DataFrame, labels: DataFrame, id_col: str = "page_id", url: str = "url", label_id: str = "doc_id",
    good: str = "quality", rules=RULES, margin: float = MARGIN,
) -> DataFrame:
    """``page_id, host, path, rule, verdict, bound``; ``good`` is the label column, 1 for good."""
    p = pages.select(F.col(id_col).alias("page_id"), F.col(url).cast("string").alias("url"))
    p = p.select("page_id", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"))
    lab = labels.where(F.col(good).isNotNull() & F.col(label_id).isNotNull()).groupBy(F.col(label_id).alias("page_id")).agg((1.0 - F.avg(F.col(good).cast("double"))).alias("bad"))
    known, rate = reputation(p.join(lab, "page_id").select("host", F.col("bad")), p.select("host").distinct())
    name, verdict = rule_of(F.col("host"), F.col("path"), rules)
    bound = F.round(F.coalesce("bound", F.lit(0.0)), 9)
    own = F.when(bound > round(margin * rate, 9), F.lit("block")).otherwise(F.lit("allow"))
    out = p.join(known.select("host", "bound"), "host", "left")
    return out.select("page_id", "host", "path", name.alias("rule"), F.coalesce(verdict, own).alias("verdict"), F.round(bound, 6).alias("bound"))


def judge_sql(margin: float = MARGIN) -> str:
    """The same in DuckDB SQL over ``pages`` and ``labels``."""
    weight = "coalesce(case when sum(n * power(bad / n - {r}, 2)) - sum({r} * (1 - {r})) > 1e-9 then least(greatest(sum(n * {r} * (1 - {r})) / (sum(n * power(bad / n - {r}, 2)) - sum({r} * (1 - {r}))) - 1, 1.0), 1e4) else 1e4 end, 1.0)"
    fits = lambda h, p: f"((host = '{h}' or ends_with(host, '.{h}')) and starts_with(path, '{p}'))"
    order = sorted(RULES, key=lambda r: -len(r[0] + r[1]))
    name = "case " + " ".join(f"when {fits(h, p)} then '{h}{p}'" for h, p, _ in order) + " end"
    verdict = "case " + " ".join(f"when {fits(h, p)} then '{v}'" for h, p, v in order) + f" when round(bound, 9) > round({margin} * r0, 9) then 'block' else 'allow' end"
    c = (Z * Z - 3) / 6
    parts = "case when len(string_split(host, '.')) > 1 then string_split(host, '.')[-2] || '.' || string_split(host, '.')[-1] else host end as domain, string_split(host, '.')[-1] as suffix"
    return f"""
with p as (select page_id, translate(coalesce(regexp_extract(url, '(?s)^.*?://([^/?#]*)([^?#]*)', 1), ''), '{UPPER}', '{LOWER}') as host,
      coalesce(regexp_extract(url, '(?s)^.*?://([^/?#]*)([^?#]*)', 2), '') as path from pages),
lab as (select doc_id as page_id, 1.0 - avg(quality::double) as bad from labels where quality is not null group by 1),
h as (select host, count(*) as n, sum(bad) as bad, {parts} from p join lab using (page_id) group by host),
d as (select domain, suffix, sum(n) as n, sum(bad) as bad from h group by 1, 2),
s as (select suffix, sum(n) as n, sum(bad) as bad from d group by 1),
z as (select coalesce(sum(bad) / sum(n), 0) as r0 from h),
s0 as (select s.*, r0 from s, z),
s1 as (select suffix, (bad + w * r0) / (n + w) as r1 from s0, (select {weight.format(r='r0')} as w from s0)),
d0 as (select d.*, r1 from d join s1 using (suffix)),
d1 as (select domain, (bad + w * r1) / (n + w) as r2 from d0, (select {weight.format(r='r1')} as w from d0)),
h0 as (select h.*, r2 from h join d1 using (domain)),
hw as (select {weight.format(r='r2')} as w from h0),
e as (select host, {parts} from (select distinct host from p)),
e1 as (select e.host, coalesce(h.n, 0) as n, coalesce(h.bad, 0) as bad, coalesce(r2, r1, r0) as r from e left join h on h.host = e.host left join d1 on d1.domain = e.domain left join s1 on s1.suffix = e.suffix, z),
e2 as (select host, bad + w * r as a, n - bad + w * (1 - r) as b from e1, hw),
e3 as (select host, a, b, 1 / (2 * a - 1) as p, 1 / greatest(2 * b - 1, 0.05) as q from e2),
e4 as (select host, a, b, p, q, 2 / (p + q) as h from e3),
k as (select host, case when a > 0.5 then a / (a + b * exp(2 * ({-Z!r} * sqrt(greatest(h + {c!r}, 0)) / h - (q - p) * ({c!r} + 5.0 / 6 - 2 / (3 * h))))) else 0 end as bound from e4)
select page_id, host, path, {name} as rule, {verdict} as verdict, round(round(bound, 9), 6) as bound from p join k using (host), z"""
