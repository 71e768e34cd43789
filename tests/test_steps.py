from relstrata.plans import workloads as w


def test_efficiency_beside_cost(spark, sf):
    rows = w.w12_steps_against_cost(spark, sf, budgets=(1000, 2000), steps=(0, 100), runs=4).collect()
    assert [(r["budget"], r["steps"]) for r in rows] == [(1000, 0), (2000, 0), (1000, 100), (2000, 100)]
    assert all(r["over_cmc"] > 0 and 0 < r["mean"] < 1 and r["runs"] == 4 for r in rows)
    assert all(r["cost_sampling"] >= r["budget"] for r in rows)
