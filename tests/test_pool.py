"""The pool keeps every complete group, whatever the largest one."""

from trajkit import scheduling

GRID = [{"name": "one", "workers": 1, "batch": 1, "queue": 99, "train_us": 0, "mode": "barrier"}]


def pool(spark, sizes):
    rows = [(100 * g + i, g, 1.0, False) for g, k in enumerate(sizes) for i in range(k)]
    return scheduling.simulate(spark.createDataFrame(rows, "rollout_id long, group_id long, latency double, failed boolean"), GRID, 4).first()


def test_a_larger_group_does_not_drop_the_others(spark):
    assert (pool(spark, [4, 5, 4, 3])["n_steps"], pool(spark, [4, 5, 4, 3])["makespan_s"]) == (3, 13 * 60.0)


def test_incomplete_groups_do_not_pass_as_complete(spark):
    assert (pool(spark, [3, 3, 2])["n_steps"], pool(spark, [3, 3, 2])["makespan_s"]) == (0, 0.0)
