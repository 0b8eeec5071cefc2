"""Exchanges of a tick, runs in memory, halos, balancing, recovery, births."""

import json

import pytest
from pyspark.sql import functions as F

from tickspace import models
from tickspace.functions import surface
from tickspace.operators import runtime, space, visible
from tickspace.operators.tick import closed_tick, tick
from tickspace.plans.agents import AgentClass, Assign, Born, Effect, Loop, State, check, histogram, invert, prepare, register_combinator, two_hop_halo
from tickspace.plans.script import ScriptError, compile_script

STRIPS = space.GridMap({"x": (-200, 100, 400)})
TREE = space.KdMap(("x", "y"), ((0,), (-100, 50)))


@pytest.fixture(scope="module")
def fish(spark):
    rows = [(i, (i * 37) % 1500 - 700, (i * 91) % 1300 - 600, i % 7 - 3, i % 5 - 2, i % 4) for i in range(150)] + [(200 + i, 0, 0, 1, 1, 2) for i in range(5)]
    return spark.createDataFrame(rows, "id bigint, x bigint, y bigint, vx bigint, vy bigint, informed bigint").cache()


def rows(df):
    return sorted(map(tuple, df.collect()))


def planned(spark, fish, classes, strategy):
    """Exchanges of a tick over a world that is held in its parts."""
    with runtime.tick_settings(spark, STRIPS.parts):
        held = runtime.hold(space.place(fish, STRIPS))
        after = tick({"fish": held.df}, classes, 0, strategy, STRIPS)["fish"]
        found = runtime.exchanges(after)
        n = after.count()
        held.free()
    assert n == fish.count()
    return found


def test_exchanges_of_a_tick(spark, fish):
    """Copies for the neighbours; effects for seen agents once more; no others."""
    assert len(planned(spark, fish, models.basic_fish(150, nonlocal_=False), "local")) == 1
    assert len(planned(spark, fish, models.school(120, 30), "local")) == 1
    assert len(planned(spark, fish, models.basic_fish(150), "nonlocal")) == 2
    assert len(planned(spark, fish, models.predator_single(150), "nonlocal")) == 2
    assert len(planned(spark, fish, models.predator_single(150, "inverted"), "local")) == 1


def test_movers_are_the_only_agents_exchanged(spark, fish):
    rules = models.basic_fish(150, nonlocal_=False)
    with runtime.tick_settings(spark, STRIPS.parts):
        staged = runtime.hold(space.place(fish, STRIPS).withColumn(runtime.NEXT, F.col(space.PART) + F.col("id").cast("int") % 2))
        assert len(runtime.exchanges(runtime._moved(staged, STRIPS.parts, True))) == 1
        staged.free()
    got = runtime.run({"fish": fish}, rules, 3, 3, "local", STRIPS, measure=True)
    full = runtime.run({"fish": fish}, rules, 3, 3, "local", STRIPS, measure=True, collocate=False)
    assert runtime.same_world(got.world["fish"], full.world["fish"])
    assert all(a["fish"] < 20 and b["fish"] == fish.count() for a, b in zip(got.exchanged, full.exchanged))


def test_plans_do_not_grow_with_the_ticks(spark, fish):
    rules, sizes = models.school(120, 30), []
    held = runtime.Holder({"fish": fish}, prepare(rules), "local", STRIPS, True, False)
    for t in range(4):
        with held.settings():
            sizes.append(len(tick({"fish": held.now["fish"].df}, rules, t, "local", STRIPS)["fish"]._jdf.queryExecution().logical().toString()))
        held.step(t)
    held.free()
    assert max(sizes) - min(sizes) < 1000


@pytest.mark.parametrize("pmap", [STRIPS, TREE])
@pytest.mark.parametrize("strategy", ["kdtree", "sweep", "nearest", "local"])
def test_kernels_mean_what_the_language_means(fish, pmap, strategy):
    rules = models.school(120, 30)
    assert runtime.same_world(tick({"fish": fish}, rules, 0, strategy, pmap)["fish"].select("id", "x", "y", "vx", "vy", "informed"), tick({"fish": fish}, rules, 0, "semantic")["fish"])


@pytest.mark.parametrize("strategy", ["sweep", "nearest", "kdtree"])
def test_traffic_by_the_nearest(spark, strategy):
    cars = spark.createDataFrame([(i, i % 5, (i * 613) % 9000 // 10 * 10, 200 + i % 90, 250 + i % 60) for i in range(300)], "id bigint, lane bigint, pos bigint, v bigint, desired bigint")
    rules = models.traffic()
    assert runtime.same_world(tick({"vehicle": cars}, rules, 0, strategy, space.GridMap({"pos": (3000, 6000)}))["vehicle"].select(*cars.columns), tick({"vehicle": cars}, rules, 0, "semantic")["vehicle"])


def test_platoon_by_hand(spark):
    """One slow leader at 500; the second brakes hard (gap 50), the third follows
    (gap 300), a lone one in lane 3 speeds up by 10 to what it desires."""
    cars = spark.createDataFrame([(1, 0, 500, 100, 100), (2, 0, 450, 300, 300), (3, 0, 150, 300, 300), (4, 3, 0, 200, 205)], "id bigint, lane bigint, pos bigint, v bigint, desired bigint")
    got = {r.id: r for r in tick({"vehicle": cars}, models.traffic(lanes=1), 0)["vehicle"].collect()}
    assert (got[1].v, got[1].pos) == (100, 510)
    assert (got[2].v, got[2].pos) == (260, 476)  # gap 50 < 80: 40 less
    assert (got[3].v, got[3].pos) == (300, 180)  # gap 300 to one of the same speed: 0 more
    assert (got[4].v, got[4].pos, got[4].lane) == (205, 20, 3)


def test_edges_of_sight(spark):
    """Agents exactly at the bound see each other, one further not; a place on a
    split has one owner."""
    f = spark.createDataFrame([(1, 90), (2, 100), (3, 111), (4, 89)], "id bigint, x bigint")
    pmap = space.GridMap({"x": (100,)})
    copies = space.replicate(f, pmap, {"x": (-10, 10)})
    assert rows(copies.where("not is_owner").select("id", "part")) == [(1, 1), (2, 0)]
    assert rows(visible.grid(f, f, {"x": (-10, 10)}).where("a_id < b_id").select("a_id", "b_id")) == [(1, 2), (1, 4)]


def test_two_hops_need_twice_the_bound(spark):
    one = "id bigint, x bigint, y bigint, energy bigint"
    world = {"predator": spark.createDataFrame([(1, 0, 0, 1)], one), "scout": spark.createDataFrame([(2, 100, 0, 1)], one), "prey": spark.createDataFrame([(3, 200, 0, 1)], one)}
    rules = invert(models.relay(100))
    assert two_hop_halo(rules) == {"x": (-200, 200), "y": (-200, 200)} and not check(rules)
    pmap = space.GridMap({"x": (200,), "y": ()})  # the prey's part begins where it is
    alarm = lambda halo: runtime.closed_ticks(world, rules, 1, pmap, {"x": (-halo, halo), "y": (-halo, halo)})["prey"].first().energy
    assert tick(world, models.relay(100), 0)["prey"].first().energy == 1
    assert alarm(200) == 1 and alarm(199) == 0 and alarm(100) == 0


def test_mirroring(spark):
    f = spark.createDataFrame([(1, 0, 0), (2, 2, 0)], "id bigint, x bigint, n bigint")
    wide = lambda b, to: {"fish": AgentClass("fish", {"x": State(), "n": State("got")}, {"got": Effect()}, (Loop("fish", {"x": b}, (Assign("got", "1", to),)),))}
    rules = wide((-1, 3), True)
    assert rows(tick({"fish": f}, rules, 0)["fish"]) == rows(tick({"fish": f}, invert(rules), 0)["fish"]) == [(1, 0, 0), (2, 2, 1)]
    assert rows(tick({"fish": f}, wide((-1, 3), False), 0)["fish"]) == [(1, 0, 1), (2, 2, 0)]  # not mirrored: another result


def test_deep_halo(fish):
    rules = models.basic_fish(100, nonlocal_=True)
    whole = runtime.run({"fish": fish}, rules, 2).world["fish"]
    halo = runtime.deep_halo(rules, 2)
    assert halo["x"] == (-440, 440)
    assert runtime.same_world(runtime.closed_ticks({"fish": fish}, rules, 2, STRIPS, halo)["fish"].select(*whole.columns), whole)
    with pytest.raises(ValueError):
        runtime.deep_halo({"f": AgentClass("f", {"x": State("x + 1")}, {"n": Effect()}, (Loop("f", {"x": (-1, 1)}, (Assign("n", "1"),)),))}, 1)


def test_balancing_is_decided(spark):
    f = spark.createDataFrame([(i, i, 0) for i in range(100)] + [(1000 + i, 900, 0) for i in range(5)], "id bigint, x bigint, y bigint")
    even = space.GridMap({"x": (250, 500, 750)})
    worth, new = runtime.review(f, even, runtime.Balance("x", 4))
    assert worth and max(r["n"] for r in runtime.owned_counts(f, new).collect()) < 40
    assert not runtime.review(f, even, runtime.Balance("x", 4, fixed=10_000))[0]
    still = {"fish": AgentClass("fish", {"x": State(), "y": State()}, {"n": Effect()}, (Loop("fish", {"x": (-1, 1)}, (Assign("n", "1"),)),))}
    got = runtime.run({"fish": f}, still, 3, strategy="local", pmap=even, balance=runtime.Balance("x", 4))
    assert got.switched == [True, False, False] and max(got.loads[0].values()) == 100 and max(got.loads[2].values()) < 40
    assert runtime.same_world(got.world["fish"], f)


def test_checkpoints_are_safe(spark, fish, tmp_path):
    path, rules = f"{tmp_path}/a", models.basic_fish(150)
    first = runtime.run({"fish": fish}, rules, 1, path=path).world["fish"]
    again = runtime.write_checkpoint({"fish": fish}, path, 1, 1)["fish"]  # a repeated epoch has data of its own
    assert runtime.same_world(first, tick({"fish": fish}, rules, 0)["fish"]) and runtime.same_world(again, fish)
    (tmp_path / "a" / "epoch=20000").mkdir()
    fish.write.parquet(f"{path}/epoch=20000/fish-x")  # broken off before its manifest
    assert runtime.resume(spark, path)[2] == 1
    runtime.write_checkpoint({"fish": fish}, path, 30_000, 7)
    assert runtime.resume(spark, path)[1:] == (7, 30_000) and runtime.resume(spark, path, 29_999)[2] == 1
    (tmp_path / "a" / "epoch=30000" / "manifest-0.json").write_text(json.dumps({"complete": True, "tick": 9, "classes": {"fish": f"{path}/gone"}}))
    assert runtime.resume(spark, path)[1] == 7


def test_storage_makes_no_difference(fish):
    rules = models.school(120, 30)
    whole = runtime.run({"fish": fish}, rules, 3, 3).world["fish"]
    assert runtime.same_world(runtime.run({"fish": fish}, rules, 3, 2, storage="disk").world["fish"], whole)
    assert runtime.same_world(runtime.run({"fish": fish}, rules, 3, 1, "local", STRIPS).world["fish"].select(*whole.columns), whole)


def test_births_and_deaths(spark):
    f = spark.createDataFrame([(1, 0, 5), (2, 50, 1), (3, 99, -1)], "id bigint, x bigint, n bigint")
    rules = {"f": AgentClass("f", {"x": State("x + 1"), "n": State("n - 1")}, die="n < 0", born=Born("n > 4", {"n": "7 + {t}"}, gap=100))}
    assert rows(tick({"f": f}, rules, 2)["f"]) == [(1, 1, 4), (2, 51, 0), (301, 1, 9)]
    spawn, _ = models.inflow(lanes=2, every=2)
    cars = spark.createDataFrame([(1, 0, 5000, 100, 100)], "id bigint, lane bigint, pos bigint, v bigint, desired bigint")
    got = runtime.run({"vehicle": cars}, models.traffic(), 2, 2, "local", space.GridMap({"pos": (1000,)}), spawn=spawn).world["vehicle"]
    assert {r.id for r in got.collect()} == {1, 10**12, 10**12 + 101}


def test_script_births():
    text = "agent f { state x = x + 1; state n; effect e : sum; each f within x [-1, 1] { e <- 1; } spawn when e > 2 { x = x - 1; } }"
    assert compile_script(text)["f"].born == Born("e > 2", {"x": "x - 1"})
    with pytest.raises(ScriptError):
        compile_script(text.replace("{ x = x - 1; }", "{ z = 1; }"))


def test_choice_of_the_join(fish):
    box = {"x": (-5, 5)}
    assert [visible.choose_join(*n) for n in ((10**6, 10**6, {}), (100, 100, box), (10**7, 500, box), (10**7, 10**7, box))] == ["nested", "nested", "broadcast", "grid"]
    rules = models.school(120, 30)
    want = tick({"fish": fish}, rules, 0, "semantic")["fish"]
    for sizes in ({"fish": 10}, {"fish": 1000}, {"fish": 10**7}):
        assert runtime.same_world(tick({"fish": fish}, rules, 0, "auto", sizes=sizes)["fish"], want)


def test_tree_of_medians(fish):
    tree = space.kd_map(fish, ["x", "y"], 3)
    counts = [r["n"] for r in runtime.owned_counts(fish, tree).collect()]
    assert tree.parts == 8 and len(counts) == 8 and max(counts) <= 25
    copies = space.replicate(fish.select("id", "x", "y"), tree, {"x": (-60, 40), "y": (-50, 50)})
    assert copies.where("is_owner").count() == fish.count()
    pairs = visible.nested_loop(fish.select("id", "x", "y"), fish.select("id", "x", "y"), {"x": (-60, 40), "y": (-50, 50)})
    assert rows(visible.kd_tree(fish.select("id", "x", "y"), fish.select("id", "x", "y"), {"x": (-60, 40), "y": (-50, 50)}, tree).select("a_id", "b_id")) == rows(pairs.select("a_id", "b_id"))


def test_ranks_without_one_window(fish):
    got = space.ranked(fish.select("informed", "x", "id"), ["informed"], ["x", "id"]).collect()
    for k in range(4):
        mine = sorted((r.x, r.id, r["rank"]) for r in got if r.informed == k)
        assert [m[2] for m in mine] == list(range(1, len(mine) + 1)) and {r.total for r in got if r.informed == k} == {len(mine)}


@pytest.mark.parametrize("m,block", [(1, 50), (3, 7), (3, 100_000)])
def test_nearest_beyond_blocks(spark, m, block):
    at = sorted((x, i) for i, x in enumerate([0, 0, 5, 49, 50, 51, 400, 2000, 2000, 2001]))
    f = spark.createDataFrame([(i, 1, x) for x, i in at] + [(99, 2, 3)], "id bigint, lane bigint, x bigint")
    want = sorted((i, k, at[n + k][1], at[n + k][0] - x) for n, (x, i) in enumerate(at) for k in range(1, m + 1) if n + k < len(at))
    assert rows(visible.nearest_ahead(f, "lane", "x", m, block)) == want


def test_combinators():
    with pytest.raises(ValueError):
        prepare({"f": AgentClass("f", {"x": State("b.x")})})
    register_combinator(histogram([3]))
    dead = prepare({"f": AgentClass("f", {"x": State("x + n")}, {"n": Effect(), "dead": Effect()}, (Loop("f", {"x": (-1, 1)}, (Assign("n", "1"),)), Loop("f", {"x": (-1, 1)}, (Assign("dead", "1"),))))})
    assert set(dead["f"].effects) == {"n"} and len(dead["f"].loops) == 1


def test_closed_ticks_exchange_nothing(spark, fish):
    with runtime.tick_settings(spark, STRIPS.parts):
        held = runtime.hold(space.place(fish, STRIPS))
        assert runtime.exchanges(closed_tick({"fish": held.df}, prepare(models.basic_fish(150)), 0, STRIPS, (space.PART,))["fish"]) == []
        held.free()


def test_functions(spark, fish):
    surface.register(spark)
    assert spark.sql("SELECT tick_floordiv(-7, 2) AS a, tick_cell(-1, 600) AS b").first() == (-4, -1)
    assert fish.where("id = 200").select(surface.heading()("vx", "vy").alias("h")).first().h == 45
    assert fish.groupBy("informed").agg(surface.middle()("id").alias("m")).count() == 4


def test_shuffled_bytes(spark, fish):
    assert runtime.shuffle_bytes(spark, lambda: fish.repartition(3, "id").count()) > 0
    assert runtime.shuffle_bytes(spark, lambda: fish.count()) < 2000
