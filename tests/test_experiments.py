"""Sweeps reproduce the shapes that do not depend on the machine."""

from tickspace import experiments as ex

SF = "/root/testdata/sf0.001"


def test_engine_equals_the_single_process_simulator(spark):
    assert [x for _, _, x in ex.validation(spark, SF, 2)] == [0.0, 0.0]


def test_replicas_grow_with_the_radius_and_movers_with_the_speed(spark):
    rows = ex.replicas(spark, SF, (100, 400), (20, 200))
    few, many, slow, fast = (x for _, _, x in rows)
    assert 0 < few < many and slow <= fast


def test_balancing_evens_the_load(spark):
    last = {s: x for s, _, x in ex.balance(spark, SF, 2)}
    assert last["balanced: load"] < last["even strips: load"]
    assert ex.as_table(spark, [("a", 1, 2.0)]).count() == 1
