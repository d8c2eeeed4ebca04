"""Workloads without a chart count in the reference score every chart of their family."""

from chartrel.plans import experiments
from chartrel.sources.families import FAMILIES

MID = "/root/testdata/sf0.01"


def test_rotation_and_width_take_every_chart(spark):
    charts = FAMILIES["supplier"](spark, MID).select("chart_id").distinct().count()
    assert charts > 60
    for f in (experiments.rotation_ablation, experiments.width_sweep):
        assert {r["n"] for r in f(spark, MID).collect()} == {charts}


def test_charts_behind_leave_out_only_the_first(spark):
    points = FAMILIES["supplier"](spark, MID)
    ids = lambda df: {r[0] for r in df.select("chart_id").distinct().collect()}
    first, rest = ids(experiments.first_charts(points, 30, 1)), ids(experiments.charts_behind(points, 30, 1))
    assert len(first) == 30 and not first & rest and first | rest == ids(points)
