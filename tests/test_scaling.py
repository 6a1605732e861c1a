"""The experiment tables on the smallest input."""

from framepatterns.workloads import scaling


def test_tables(spark, sf):
    s = scaling.strong_scaling_table(spark, sf, [1, 2], copies=2, reps=1)
    assert {r["operator"] for r in s} == {"scalar", "scalar aggregation", "group-by", "join"} and all(r["seconds"] for r in s)
    c = scaling.cardinality_table(spark, sf, 4, reps=1)
    by = {(r["C"], r["pattern"]): r for r in c}
    assert by[1e-5, "combine"]["rows"] < by[1e-5, "shuffle"]["rows"] / 100
    assert by[1e-5, "combine"]["choice"] == "combine" and by[0.9, "combine"]["choice"] == "shuffle"
    assert scaling.markdown(c).count("\n") == len(c) + 1


def test_sorts_stay_even(spark, sf):
    rows = scaling.sort_table(spark, sf, 4, copies=3, reps=1)
    assert len(rows) == 6 and all(r["max_over_mean"] <= 2.0 for r in rows if r["algorithm"] != "native")
