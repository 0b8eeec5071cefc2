"""Strategies agree, rewrites change nothing, classes are checked statically."""

import pytest
from pyspark.sql import functions as F

from tickspace import models
from tickspace.operators import runtime, space, visible
from tickspace.operators.tick import naive_sql, tick
from tickspace.plans.agents import AgentClass, Assign, Combinator, Effect, Loop, State, check, drop_dead_effects, fuse_loops, invert, register_combinator

STRIPS = space.GridMap({"x": (-10, 0, 500)})


@pytest.fixture(scope="module")
def fish(spark):
    rows = [(i, (i * 37) % 1500 - 700, (i * 91) % 1300 - 600, i % 7 - 3, i % 5 - 2, i % 4) for i in range(120)] + [(200 + i, 0, 0, 1, 1, 2) for i in range(5)]
    return spark.createDataFrame(rows, "id bigint, x bigint, y bigint, vx bigint, vy bigint, informed bigint").cache()


def rows(df):
    return sorted(map(tuple, df.collect()))


def test_join_strategies_agree(fish):
    f, box = fish.select("id", "x", "y"), {"x": (-100, 60), "y": (-80, 90)}
    want = rows(visible.nested_loop(f, f, box).select("a_id", "b_id"))
    assert rows(visible.grid(f, f, box).select("a_id", "b_id")) == want
    assert rows(visible.two_level(f, f, box, STRIPS).select("a_id", "b_id")) == want
    assert rows(visible.kd_tree(f, f, box, STRIPS).select("a_id", "b_id")) == want
    assert rows(visible.broadcast_small(f, f, box, 10).select("a_id", "b_id")) == want


def test_replicas_and_single_ownership(fish):
    copies = space.replicate(fish, STRIPS, {"x": (-50, 50)})
    assert copies.where("is_owner").count() == fish.count()
    assert copies.where("not is_owner and abs(x + 10) > 51 and abs(x) > 51 and abs(x - 500) > 51").count() == 0


@pytest.mark.parametrize("strategy", ["grid", "local", "nonlocal"])
@pytest.mark.parametrize("world", [models.basic_fish(150), models.basic_fish(150, nonlocal_=False), models.school(120, 30)])
def test_runtime_means_what_the_language_means(fish, strategy, world):
    want = tick({"fish": fish}, world, 0, "semantic")["fish"]
    assert runtime.same_world(tick({"fish": fish}, world, 0, strategy, STRIPS)["fish"], want)


def test_inversion_mirrors_the_bound_and_saves_an_exchange(fish):
    loop = Loop("fish", {"x": (-1, 3)}, (Assign("n", "a.vx + 2 * b.vx", True),))
    world = {"fish": AgentClass("fish", {c: State() for c in ("x", "y", "vx", "vy", "informed")}, {"n": Effect()}, (loop,))}
    back = invert(world)["fish"].loops[0]
    assert back.bound == {"x": (-3, 1)} and back.assigns[0].value == "b.vx + 2 * a.vx" and not back.assigns[0].to_seen
    assert not check(world)


def test_static_checks():
    bad = AgentClass("a", {"x": State("b.x"), "e": State()}, {"e": Effect("first")}, (Loop("a", {"x": (2, 1)}, (Assign("x", "a.e"), Assign("zz", "1"))),))
    found = " ".join(check({"a": bad}))
    for code in ("UNTAGGED_FIELD", "NO_COMBINATOR", "FOREIGN_READ_IN_UPDATE", "BAD_BOUND", "STATE_WRITE_IN_QUERY", "EFFECT_READ_IN_LOOP", "UNKNOWN_FIELD"):
        assert code in found
    with pytest.raises(ValueError):
        register_combinator(Combinator("last", None, None))
    with pytest.raises(ValueError):
        register_combinator(Combinator("minus", None, None, 0), [1, 2], lambda x, y: x - y)


def test_rewrites():
    loop = Loop("a", {"x": (-1, 1)}, (Assign("n", "1"),))
    c = AgentClass("a", {"x": State("x + n")}, {"n": Effect(), "dead": Effect()}, (loop, Loop("a", {"x": (-1, 1)}, (Assign("dead", "1"),))))
    assert len(fuse_loops(c).loops) == 1
    assert set(drop_dead_effects({"a": c})["a"].effects) == {"n"}


def test_recovery_equals_an_uninterrupted_run(spark, fish, tmp_path):
    world = models.basic_fish(150)
    whole = runtime.run({"fish": fish}, world, 3, path=f"{tmp_path}/a").world["fish"]
    runtime.run({"fish": fish}, world, 2, path=f"{tmp_path}/b")
    got, at, epoch = runtime.resume(spark, f"{tmp_path}/b")
    assert (at, epoch) == (2, 2)
    assert runtime.same_world(runtime.run(got, world, 3, path=f"{tmp_path}/b", start_tick=at, start_epoch=epoch).world["fish"], whole)


def test_empty_extent(fish):
    none = fish.where("false")
    assert tick({"fish": none}, models.basic_fish(100), 0)["fish"].count() == 0


def test_measures():
    assert round(runtime.loglog_slope([1, 2, 4], [3, 12, 48]), 6) == 2
    assert runtime.stable_window([9, 5, 1.0, 1.01, 0.99]) == 2
    assert runtime.scaleup({1: 2.0, 4: 6.0})[4] == 0.75
    best = min(range(50, 4000, 10), key=lambda i: runtime.expected_runtime(1e5, i, 10, 3600))
    assert abs(best - runtime.optimal_interval(10, 3600)) / best < 0.05
    assert space.should_repartition([10, 2], [6, 6], 4, 5) and not space.should_repartition([7, 5], [6, 6], 40, 5)


def test_sql_lowering_is_one_statement():
    assert naive_sql(models.traffic(), {"vehicle": "SELECT 1"}, 1, "SELECT * FROM vehicle_1").startswith("WITH")


def test_pair_counts_in_queries(spark):
    from tickspace.queries import QUERIES, SQL

    assert set(SQL) <= set(QUERIES)
    assert QUERIES["q_visible_grid"](spark, "/root/testdata/sf0.001").agg(F.sum("n")).first() == QUERIES["q_visible_two_level"](spark, "/root/testdata/sf0.001").agg(F.sum("n")).first()
