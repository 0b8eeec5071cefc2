"""Crowded extents: the same results without the pairs."""

import tracemalloc

import numpy as np
import pytest
from pyspark.sql import functions as F

from tickspace import models, queries
from tickspace.baseline import traffic_numpy
from tickspace.functions import surface
from tickspace.operators import dense, folds, runtime, space, visible
from tickspace.operators.tick import attach, closed_tick, prepare, query_phase, tick
from tickspace.plans.agents import Assign, Effect, Loop
from tickspace.plans.script import compile_script
from tickspace.streaming import sightings

STRIPS = space.GridMap({"x": (-10, 0, 500)})


@pytest.fixture(scope="module")
def crowd(spark):
    """Few places, many fish, some of them alone."""
    rows = [(i, (i * 37) % 1500 - 700 if i % 3 else i % 5, (i * 91) % 1300 - 600 if i % 3 else 7, i % 7 - 3, i % 5 - 2, i % 4) for i in range(300)] + [(900, 10**6, 10**6, 1, 1, 1)]
    return spark.createDataFrame(rows, "id bigint, x bigint, y bigint, vx bigint, vy bigint, informed bigint").cache()


@pytest.mark.parametrize("few", [0, 1 << 22])
@pytest.mark.parametrize("strategy", ["grid", "local", "nonlocal"])
@pytest.mark.parametrize("nonlocal_", [True, False])
def test_sums_over_crowded_boxes_make_no_pairs(crowd, monkeypatch, few, strategy, nonlocal_):
    """Fish were compared pair by pair."""
    world = models.basic_fish(150, nonlocal_=nonlocal_)
    want = tick({"fish": crowd}, world, 0, "semantic")["fish"]
    monkeypatch.setattr(dense, "CROWDED", 1)
    monkeypatch.setattr(dense, "FEW", few)
    got = tick({"fish": crowd}, world, 0, strategy, STRIPS)["fish"]
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "CoGroup" in plan and "cell_x" not in plan and "ca_x" not in plan
    assert runtime.same_world(got, want)


def test_sums_in_closed_parts_make_no_pairs(crowd, monkeypatch):
    """so they were in parts that exchange nothing."""
    world = prepare(models.basic_fish(150))
    monkeypatch.setattr(dense, "CROWDED", 1)
    with runtime.tick_settings(crowd.sparkSession, STRIPS.parts):
        plan = closed_tick({"fish": space.place(crowd, STRIPS)}, world, 0, STRIPS, (space.PART,))["fish"]._jdf.queryExecution().executedPlan().toString()
    assert "CoGroup" in plan and "ca_x" not in plan
    want = runtime.run({"fish": crowd}, world, 2).world["fish"]
    assert runtime.same_world(runtime.closed_ticks({"fish": crowd}, world, 2, STRIPS, runtime.deep_halo(world, 2))["fish"], want)


def test_scripts_are_separable_too():
    """the script's forces depend on one axis each."""
    c = compile_script(queries.FISH_SCRIPT)["fish"]
    found = dense.separable(c.loops[0], [(x, c.effects[x.effect]) for x in c.loops[0].assigns])
    assert {e: axis for e, (axis, _) in found.items()} == {"ax": "x", "ay": "y", "cnt": "x"}


def test_what_is_not_separable_goes_by_pairs():
    for c in (models.school()["fish"], models.follow_leader()["fish"]):
        assert dense.separable(c.loops[0], [(x, c.effects[x.effect]) for x in c.loops[0].assigns]) is None


def test_meetings_join_by_slot_of_time(spark):
    """all sightings of a kind were compared with each other."""
    rows = spark.sql("SELECT id AS event_id, timestamp_seconds(id * 150) AS ts, id % 3 AS user_id, 'view' AS event_type, 1.0 AS value FROM range(40)")
    got = sightings.meetings(rows, rows)
    assert "slot" in next(line for line in got._jdf.queryExecution().executedPlan().toString().split("\n") if "Join" in line)
    assert {tuple(r) for r in got.collect()} == {(i, j) for i in range(40) for j in range(i, min(40, i + 3)) if i % 3 != j % 3}


def test_places_stand_for_their_fish(crowd):
    """pairs were made of fish, though many share a place."""
    met = []

    def find(a, b):
        met.append(a.count())
        return visible.nested_loop(a, b, {"x": (-100, 100), "y": (-100, 100)})

    xy = crowd.select("id", "x", "y")
    got = queries._count_places(xy, find)
    assert met[0] == xy.select("x", "y").distinct().count() < xy.count()
    assert runtime.same_world(got, queries._count(visible.nested_loop(xy, xy, {"x": (-100, 100), "y": (-100, 100)})))


def test_nearest_others_of_a_crowded_place(crowd):
    """all pairs of a crowded place were sorted."""
    at = {r.id: (r.x, r.y) for r in crowd.collect()}
    d2 = lambda i, j: sum((p - q) ** 2 for p, q in zip(at[i], at[j]))
    near = {i: sorted((d2(i, j), j) for j in at if i != j and all(abs(p - q) <= 90 for p, q in zip(at[i], at[j])))[:3] for i in at}
    assert {tuple(r) for r in visible.nearest_others(crowd, "x", "y", 90, 3).collect()} == {(i, k + 1, j) for i, n in near.items() for k, (_, j) in enumerate(n)}


def test_sql_tick_meets_places(crowd):
    """fish at one place were looked up one by one."""
    surface.register(crowd.sparkSession)
    crowd.createOrReplaceTempView("crowd")
    text = surface.fish_tick("crowd", 150, 60, 1000)
    assert "GROUP BY x, y" in text
    want = tick({"fish": crowd}, models.basic_fish(150), 0, "semantic")["fish"]
    assert runtime.same_world(crowd.sparkSession.sql(text), want)


def test_single_process_traffic_by_blocks(spark):
    """all vehicles came to the driver's process."""
    cars = spark.range(400).selectExpr("id", "id * 7 % 5 AS lane", "id * 997 % 9000 AS pos", "200 + id % 130 AS v", "200 + id % 130 AS desired")
    got = traffic_numpy(cars, 3, block=700)
    assert "FlatMapGroupsInArrow" in got._jdf.queryExecution().executedPlan().toString()
    assert runtime.same_world(got, runtime.run({"vehicle": cars}, models.traffic(), 3, epoch_len=3).world["vehicle"])


@pytest.mark.parametrize("how", ["kdtree", "sweep", "all"])
def test_kernels_work_on_blocks_of_a_part(crowd, how):
    """one call compared a whole part, however crowded."""
    xy, one = crowd.select("id", "x", "y"), space.GridMap({"x": ()})
    got = visible.kd_tree(xy, xy, {"x": (-20, 10), "y": (-5, 30)}, one, how)
    assert "_in_x" in got._jdf.queryExecution().executedPlan().toString()
    assert runtime.same_world(got.select("a_id", "b_id"), visible.nested_loop(xy, xy, {"x": (-20, 10), "y": (-5, 30)}).select("a_id", "b_id"))


@pytest.mark.parametrize("strategy", ["semantic", "kdtree", "sweep"])
def test_kinds_stand_for_their_agents(crowd, strategy):
    """F1, F2, F16: pairs were made of agents that a loop cannot tell apart."""
    more = crowd.unionByName(crowd.selectExpr("id + 1000 AS id", "x", "y", "vx", "vy", "informed"))
    world = models.school(120, 30)
    got = tick({"fish": more}, world, 0, strategy, STRIPS)["fish"]
    assert "_n#" in got._jdf.queryExecution().optimizedPlan().toString()
    assert runtime.same_world(got, tick({"fish": more}, world, 0, "grid")["fish"])


def test_followers_look_at_the_closest_only(crowd):
    """Followers were compared with all in sight."""
    flock = crowd.selectExpr("id", "x", "y", "vx", "vy", "CASE WHEN id % 3 = 0 THEN id + 1 ELSE -1 END AS leader")
    got = tick({"fish": flock}, models.follow_leader(200), 0)["fish"]
    assert got._jdf.queryExecution().optimizedPlan().toString().count("b_ids") > 0
    assert runtime.same_world(got, tick({"fish": flock}, models.follow_leader(200), 0, "semantic")["fish"])


@pytest.mark.parametrize("how", list(visible.BATCHES))
def test_kernels_fold_pairs_in_batches(how):
    """A kernel held all pairs of a block (here 16 million, 256 MB of places)."""
    at = np.stack([np.arange(4000) * 7 % 601, np.arange(4000) * 11 % 601], 1)
    low, high, one = np.array([-600, -600]), np.array([600, 600]), np.ones(4000, np.int64)
    table = folds.Fold((folds.Term("b_n", 0, "b_n"),), (((0, 1), np.ones(1201 * 1201, np.int16)),))
    for fold in (folds.sums("n"), table):
        tracemalloc.start()
        n, sums = fold.run(visible.BATCHES[how], at, at, low, high, one, [], [one], None)
        assert tracemalloc.get_traced_memory()[1] < 150 << 20
        tracemalloc.stop()
        assert (n == 4000).all() and (sums == 4000).all()


@pytest.mark.parametrize("how", ["kdtree", "sweep", "all"])
def test_kd_tree_sums_without_pairs(crowd, how):
    """pairs of places came back as rows, however many."""
    xy = crowd.selectExpr("id", "x", "y", "CASE WHEN id % 5 = 0 THEN NULL ELSE id - 150 END AS v").unionByName(crowd.selectExpr("id + 1000 AS id", "CAST(NULL AS BIGINT) AS x", "y", "id AS v").limit(2))
    box, strips = {"x": (-20, 10), "y": (-5, 30)}, space.GridMap({"x": (0,)})
    got = visible.kd_tree(xy, xy, box, strips, how, folds.sums("id", "v"))
    want = visible.nested_loop(xy, xy, box).groupBy("a_id", "a_x", "a_y", "a_v").agg(F.sum("b_id").alias("b_id"), F.coalesce(F.sum("b_v"), F.lit(0)).alias("b_v"))
    assert got.count() > 0 and runtime.same_world(got, want)
    assert "b_x" not in got.columns and "_in_x" in got._jdf.queryExecution().executedPlan().toString()


def test_sums_beyond_64_bits_stop():
    """What summing pairs as rows does too."""
    at, low, high = np.zeros((4, 1), np.int64), np.array([0]), np.array([0])
    big = np.array([1 << 62, 1 << 62, -(1 << 62), 5])
    assert folds.sums("n").run(visible.BATCHES["kdtree"], at, at, low, high, np.ones(4), [], [big], None)[1].tolist() == [[(1 << 62) + 5] * 4]
    with pytest.raises(OverflowError):
        folds.sums("n").run(visible.BATCHES["sweep"], at, at, low, high, np.ones(4), [], [np.abs(big)], None)


@pytest.mark.parametrize("strategy", ["semantic", "kdtree", "sweep"])
def test_loops_sum_in_the_kernel(crowd, strategy):
    """Pairs were joined, or handed out by the kernels, as rows."""
    some = crowd.selectExpr("id", "x", "y", "CASE WHEN id % 9 = 0 THEN NULL ELSE vx END AS vx", "vy", "informed")
    for world in (models.school(120, 30), models.basic_fish(150)):
        if strategy != "semantic" and world["fish"].loops[0].assigns[0].to_seen:
            continue
        want = attach(some, world["fish"], query_phase({"fish": some}, world, "grid")["fish"])
        got = attach(some, world["fish"], query_phase({"fish": some}, world, strategy, STRIPS)["fish"])
        plan = got._jdf.queryExecution().optimizedPlan().toString()
        assert "CoGroup" in plan and "b_vx >= " not in plan and "b_x#" not in plan.split("CoGroup")[0]
        assert runtime.same_world(got.select(*want.columns), want)


def test_what_is_no_sum_of_products_goes_by_pairs(crowd):
    for value in ("b.vx * a.vy", "CASE WHEN b.vx > 0 THEN 1 ELSE 0 END + a.id", "rand()"):
        loop = Loop("fish", {"x": (-9, 9)}, (Assign("e", value),))
        assert folds.plan(crowd, loop, [(loop.assigns[0], Effect())], False, "b__n") is None


@pytest.mark.parametrize("share", [0, 0.001, 0.3, 1])
def test_places_of_set_bytes(share):
    """the few pairs that pass were looked for byte by byte."""
    for n in (0, 5, 4097, 70001):
        some = np.random.default_rng(n).random(n) < share
        assert visible._set_places(some).tolist() == np.flatnonzero(some).tolist()


def test_nested_loops_fold_blocks(crowd):
    """every pair was tested in one join, a row each."""
    xy, box = crowd.select("id", "x", "y"), {"x": (-20, 10), "y": (-5, 30)}
    want = visible.nested_loop(xy, xy, box).groupBy("a_id", "a_x", "a_y").agg(F.sum("b_id").alias("b_id"))
    got = visible.nested_loop(xy, xy, box, folds.sums("id"), rows=70)
    assert "NestedLoopJoin" not in got._jdf.queryExecution().executedPlan().toString()
    assert runtime.same_world(got, want)
