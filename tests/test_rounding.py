"""Bernoulli rounding draws for all lengths by one expression, which is as small for long plans."""

from pyspark.sql import functions as F

from echowalk.functions.rng import SPAN, draw_local
from echowalk.functions.sampling import SamplingPlan


def test_bernoulli_lengths(spark):
    plan = SamplingPlan.create(10_000, 0.6, 0.3, rounding="bernoulli")
    lens = plan.lengths_of(F.col("id"), 7)
    assert lens._jc.toString().count("md5") == 1
    for r in spark.range(5).select("id", lens.alias("lens")).collect():
        more = [draw_local(7, "round", r["id"], i) < int((x - k) * SPAN) for i, (x, k) in enumerate(zip(plan.ideal, plan.actual))]
        assert r["lens"] == [i for i, k in enumerate(plan.actual) for _ in range(k + more[i])]
