"""The similarity measure as column expressions, with a SQL form of each.

A matched pair of cosine ``c`` costs ``base**(1 - c) - 1``.  The sum of costs is
turned back by a logarithm into a smooth minimum of the cosines: one substitution
gives its cosine, identical tokens add nothing, and the plain minimum is the limit
of a large base.  Every inserted or deleted token multiplies by ``exp(-v / (m k))``.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

BASE = 1e4
NTH, REFERENCE = 50, 5  # calibration: this lowest norm, at this query length, gives 1/e


def cost(c: Column, base: float = BASE) -> Column:
    return F.pow(F.lit(base), 1 - c) - 1


def smooth_min(total_cost: Column, base: float = BASE) -> Column:
    """From the sum of costs; never below 0."""
    return F.greatest(F.lit(0.0), 1 - F.log1p(total_cost) / math.log(base))


def similarity(total_cost: Column, log_penalty: Column, base: float = BASE) -> Column:
    """Rounded to six places, so that thresholds decide alike in every engine."""
    return F.round(smooth_min(total_cost, base) * F.exp(log_penalty), 6)


def soft_min(cosines: Column, base: float = BASE) -> Column:
    total = F.aggregate(cosines, F.lit(0.0), lambda s, c: s + cost(c, base))
    return smooth_min(total, base)


def hard_min(cosines: Column) -> Column:
    return F.array_min(cosines)


def cosine(a: Column, b: Column) -> Column:
    dot = lambda x, y: F.aggregate(F.zip_with(x.cast("array<double>"), y.cast("array<double>"), lambda p, q: p * q), F.lit(0.0), lambda s, v: s + v)
    return dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))


def register_sql(spark: SparkSession) -> None:
    """``soft_min``, ``hard_min``, ``edit_penalty``, ``cosine_of`` and ``tokenize`` as SQL functions."""
    ln = math.log(BASE)
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION soft_min(cs ARRAY<DOUBLE>) RETURNS DOUBLE RETURN greatest(0D, 1 - ln(1 + aggregate(cs, 0D, (s, c) -> s + pow({BASE}, 1 - c) - 1)) / {ln})")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION hard_min(cs ARRAY<DOUBLE>) RETURNS DOUBLE RETURN array_min(cs)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION edit_penalty(v DOUBLE, m INT, k DOUBLE) RETURNS DOUBLE RETURN exp(-v / (m * k))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION cosine_of(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, v) -> s + v) / sqrt(aggregate(a, 0D, (s, v) -> s + v * v) * aggregate(b, 0D, (s, v) -> s + v * v))")
    spark.sql(r"CREATE OR REPLACE TEMPORARY FUNCTION tokenize(t STRING) RETURNS ARRAY<STRING> RETURN regexp_extract_all(lower(t), '[\\p{L}\\p{N}]+|[^\\s\\p{L}\\p{N}]', 0)")


# ------------------------------------------------------ one pair, with alignment
def align(q: list[str], p: list[str], cos, norm, kappa: float, base: float = BASE, edits: str = "both") -> tuple[float, list[tuple]]:
    """Best similarity of a query and a pattern over all alignments, and its edit script.

    States are sets of (sum of costs, log penalty) of which none is worse in both;
    keeping one best score would lose alignments that win later.  ``cos`` and
    ``norm`` are functions of tokens.
    """
    m = len(q)
    grid: dict[tuple[int, int], list[tuple[float, float, tuple]]] = {(0, 0): [(0.0, 0.0, ())]}

    def put(at: tuple[int, int], state: tuple[float, float, tuple]) -> None:
        held = grid.setdefault(at, [])
        if any(s[0] <= state[0] and s[1] >= state[1] for s in held):
            return
        held[:] = [s for s in held if not (state[0] <= s[0] and state[1] >= s[1])]
        held.append(state)

    for i in range(m + 1):
        for j in range(len(p) + 1):
            for s, lp, ops in grid.get((i, j), []):
                if i < m and j < len(p):
                    c = cos(q[i], p[j])
                    put((i + 1, j + 1), (s + base ** (1 - c) - 1, lp, (*ops, ("keep" if q[i] == p[j] else "sub", q[i], p[j], c))))
                if i < m and edits in ("both", "del"):
                    f = -norm(q[i]) / (m * kappa)
                    put((i + 1, j), (s, lp + f, (*ops, ("del", q[i], None, math.exp(f)))))
                if j < len(p) and edits in ("both", "ins"):
                    f = -norm(p[j]) / (m * kappa)
                    put((i, j + 1), (s, lp + f, (*ops, ("ins", None, p[j], math.exp(f)))))
    ends = grid.get((m, len(p)), [])
    if not ends:
        return 0.0, []
    best = max(ends, key=lambda s: max(0.0, 1 - math.log1p(s[0]) / math.log(base)) * math.exp(s[1]))
    return max(0.0, 1 - math.log1p(best[0]) / math.log(base)) * math.exp(best[1]), list(best[2])
