import math

import pytest
from pyspark.sql import functions as F

from ngramlake.functions import similarity as sim

BASE = 1e4


def smooth(cs):
    return max(0.0, 1 - math.log1p(sum(BASE ** (1 - c) - 1 for c in cs)) / math.log(BASE))


def test_worked_values():
    assert round(smooth([0.63, 0.85]), 2) == 0.62
    assert round(smooth([0.891, 0.864]), 3) == 0.820
    assert smooth([1.0, 0.7, 1.0]) == pytest.approx(0.7)


def test_column_forms(spark):
    sim.register_sql(spark)
    row = spark.range(1).select(
        sim.soft_min(F.array(F.lit(0.63), F.lit(0.85))).alias("s"), sim.hard_min(F.array(F.lit(0.63), F.lit(0.85))).alias("h"),
        F.expr("soft_min(array(0.63D, 0.85D))").alias("q"), F.expr("edit_penalty(108.5D, 5, 21.7D)").alias("e"),
        sim.cosine(F.array(F.lit(1.0), F.lit(0.0)), F.array(F.lit(1.0), F.lit(1.0))).alias("c"), F.expr("size(tokenize('A b, c'))").alias("n"),
    ).first()
    assert row.s == pytest.approx(smooth([0.63, 0.85])) == row.q
    assert row.h == 0.63 and row.e == pytest.approx(1 / math.e) and row.c == pytest.approx(math.sqrt(0.5)) and row.n == 4


def test_published_penalties():
    # squared norms implied by the published rows, with m = 5 and constant 21.70; all below the 50th-lowest
    for percent, norm in ((0.854, 17.1), (0.842, 18.7), (0.751, 31.1)):
        assert math.exp(-norm / (5 * 21.70)) == pytest.approx(percent, abs=0.001)
        assert norm < 5 * 21.70


def test_alignment_needs_both_numbers():
    cos = lambda a, b: 1.0 if a == b else 0.5
    norm = lambda t: 2.0
    same, script = sim.align(["a", "b"], ["a", "b"], cos, norm, 1.0)
    assert same == pytest.approx(1.0) and [s[0] for s in script] == ["keep", "keep"]
    gone, script = sim.align(["a", "x", "b"], ["a", "b"], cos, norm, 10.0)
    assert gone == pytest.approx(math.exp(-2 / 30)) and "del" in [s[0] for s in script]
    put, script = sim.align(["a", "b"], ["a", "x", "b"], cos, norm, 10.0)
    assert put == pytest.approx(math.exp(-2 / 20)) and "ins" in [s[0] for s in script]
    assert sim.align(["a"], ["a", "b"], cos, norm, 10.0, edits="none")[0] == 0.0
