"""The experiment workloads as sweeps: each gives rows (setting, value, seconds or
a count).  Times are wall seconds of one action, the median of ``REPEATS`` after a
warm-up; counts do not depend on the machine.

    python -m tickspace.experiments /root/testdata/sf0.1 growth visibility ...
"""

from __future__ import annotations

import statistics
import sys
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import models
from .baseline import traffic_numpy
from .operators import runtime, space, visible
from .operators.tick import World, tick
from .plans.agents import AgentClass, invert
from .sources.adapters import EXTENTS

Row = tuple[str, int, float]


REPEATS = 3


def seconds(make: Callable[[], DataFrame], repeats: int = REPEATS) -> float:
    """Median wall seconds until every row of ``make()`` is computed."""
    took = []
    for _ in range(repeats):
        began = time.perf_counter()
        make().write.format("noop").mode("overwrite").save()
        took.append(time.perf_counter() - began)
    return round(statistics.median(took), 3)


def _held(spark: SparkSession, df: DataFrame) -> DataFrame:
    path = space.scratch(spark, "extent")
    df.write.parquet(path)
    return spark.read.parquet(path)


def _tick_seconds(world: World, classes: dict[str, AgentClass], cls: str, strategy: str, pmap=None, repeats: int = REPEATS) -> float:
    return seconds(lambda: tick(world, classes, 0, strategy, pmap)[cls], repeats)


def _in_parts(spark: SparkSession, world: World, classes: dict[str, AgentClass], cls: str, strategy: str, pmap) -> tuple[float, int, int]:
    """(seconds, exchanges, bytes shuffled) of a tick over a world held in parts."""
    with runtime.tick_settings(spark, pmap.parts):
        held = {n: runtime.hold(space.place(df, pmap)) for n, df in world.items()}
        after = lambda: tick({n: h.df for n, h in held.items()}, classes, 0, strategy, pmap)[cls]
        seconds(after, 1)
        took, sent = seconds(after), runtime.shuffle_bytes(spark, lambda: seconds(after, 1))
        count = runtime.exchange_count(after())
        for h in held.values():
            h.free()
    return took, count, sent


def tile(agents: DataFrame, times: int, axis: str, width: int, gap: int = 10**9) -> DataFrame:
    """The extent ``times`` times beside itself: more agents at the same density."""
    copies = agents.withColumn("_k", F.explode(F.sequence(F.lit(0), F.lit(times - 1))))
    return copies.withColumn(axis, F.col(axis) + F.col("_k") * width).withColumn("id", F.col("id") + F.col("_k") * gap).drop("_k")


def growth(spark: SparkSession, sf_dir: str, sizes: tuple[int, ...] = (10_000, 20_000, 40_000), nested_up_to: int = 40_000) -> list[Row]:
    """Traffic: one tick by segment length, for the single-process simulator, the
    engine without and with an index (cells, median trees, sorted sweep, nearest).
    A shorter segment is the stretch of road from its start, so that the density
    stays."""
    road = _held(spark, EXTENTS["vehicle"](spark, sf_dir))
    n, end = road.agg(F.count("*"), F.max("pos")).first()
    out: list[Row] = []
    rules, series = models.traffic(), {}
    for size in sizes:
        part = _held(spark, road.where(F.col("pos") <= end * size // n))
        if not series:
            for warm in ("grid", "semantic"):
                _tick_seconds({"vehicle": part.limit(100)}, rules, "vehicle", warm)
            seconds(lambda: traffic_numpy(part, 1))
        series.setdefault("single process", []).append(seconds(lambda: traffic_numpy(part, 1)))
        series.setdefault("grid", []).append(_tick_seconds({"vehicle": part}, rules, "vehicle", "grid"))
        pmap = space.initial_partition(part, ["pos"], 8)
        for how in ("kdtree", "sweep", "nearest"):
            series.setdefault(how, []).append(_tick_seconds({"vehicle": part}, rules, "vehicle", how, pmap))
        if size <= nested_up_to:
            series.setdefault("nested", []).append(_tick_seconds({"vehicle": part}, rules, "vehicle", "semantic"))
    for name, took in series.items():
        out += [(name, s, t) for s, t in zip(sizes, took)]
        if len(took) > 1:
            out.append((f"{name}: slope", 0, round(runtime.loglog_slope(list(sizes[: len(took)]), took), 2)))
    return out


def growth_fish(spark: SparkSession, sf_dir: str, times: tuple[int, ...] = (1, 2, 4), nested_up_to: int = 2) -> list[Row]:
    """School: one tick by the number of fish at one density."""
    fish = _held(spark, EXTENTS["fish"](spark, sf_dir).where("id < 10000"))
    low, high = fish.agg(F.min("x"), F.max("x")).first()
    rules, series, sizes = models.school(), {}, []
    for k in times:
        some = _held(spark, tile(fish, k, "x", high - low + 1000))
        sizes.append(some.count())
        pmap = space.initial_partition(some, ["x"], 8)
        for how in ("grid", "kdtree", *(("semantic",) if k <= nested_up_to else ())):
            series.setdefault(how, []).append(_tick_seconds({"fish": some}, rules, "fish", how, pmap))
    out: list[Row] = []
    for name, took in series.items():
        out += [(name, n, t) for n, t in zip(sizes, took)]
        if len(took) > 1:
            out.append((f"{name}: slope", 0, round(runtime.loglog_slope(sizes[: len(took)], took), 2)))
    return out


def visibility(spark: SparkSession, sf_dir: str, radii: tuple[int, ...] = (75, 150, 300, 600, 1200)) -> list[Row]:
    """Fish: one tick by visible radius, without an index, with cells and with
    median trees, and the pairs that an index finds."""
    fish = {"fish": _held(spark, EXTENTS["fish"](spark, sf_dir).where("id < 10000"))}
    pmap = space.kd_map(fish["fish"], ["x", "y"], 3)
    for how in ("grid", "kdtree", "semantic"):
        _tick_seconds(fish, models.school(rho=radii[0]), "fish", how, pmap, 1)
    out: list[Row] = []
    for r in radii:
        rules = models.school(rho=r)
        slow, fast, tree = (_tick_seconds(fish, rules, "fish", s, pmap) for s in ("semantic", "grid", "kdtree"))
        xy = fish["fish"].select("id", "x", "y")
        found = visible.grid(xy, xy, {"x": (-r, r), "y": (-r, r)}).count() - xy.count()
        out += [("nested", r, slow), ("grid", r, fast), ("kdtree", r, tree), ("gain", r, round(slow / min(fast, tree), 2)), ("pairs", r, found)]
    return out


def inversion(spark: SparkSession, sf_dir: str, parts: int = 16) -> list[Row]:
    """Predators, of two classes and of one, in 16 parts: index off (all pairs of
    a part) and on, times two reduce passes and one; gains, exchanges and bytes."""
    out: list[Row] = []
    two = {n: _held(spark, EXTENTS[n](spark, sf_dir)) for n in ("prey", "predator")}
    one = {"fish": _held(spark, EXTENTS["fish"](spark, sf_dir))}
    for name, world, cls, make in (("two classes", two, "prey", models.predator), ("one class", one, "fish", models.predator_single)):
        pmap = space.initial_partition(world[cls], ["x", "y"], int(parts**0.5))
        took = {}
        for passes, rules, strategy in (("two passes", make(), "nonlocal"), ("one pass", make(variant="inverted"), "local")):
            for index, how in (("index", strategy), ("no index", "all")):
                took[passes, index], n, sent = _in_parts(spark, world, rules, cls, how, pmap)
                out += [(f"{name}, {passes}, {index}", 0, took[passes, index]), (f"{name}, {passes}, {index}: exchanges", 0, n), (f"{name}, {passes}, {index}: bytes", 0, sent)]
        for index in ("index", "no index"):
            out.append((f"{name}, {index}: gain of inversion", 0, round(took["two passes", index] / took["one pass", index], 2)))
    return out


def scale_up(spark: SparkSession, sf_dir: str, workers: tuple[int, ...] = (1, 2, 4, 8), model: str = "traffic", ticks: int = 3) -> list[Row]:
    """Size in proportion to the parts (one task each): agent ticks a second, as
    shares of linear growth, and the agents that change place a tick.  ``model``:
    ``traffic``, or ``school`` without and with balancing."""
    out: list[Row] = []
    name, cls, axis, rules = ("vehicle", "vehicle", "pos", models.traffic()) if model == "traffic" else ("fish", "fish", "x", models.school(speed=400))
    base = _held(spark, EXTENTS[name](spark, sf_dir).where("id < 20000"))
    low, high = base.agg(F.min(axis), F.max(axis)).first()
    for kind in ("even",) if model == "traffic" else ("even", "balanced"):
        series = {}
        for w in workers:
            world = {cls: _held(spark, tile(base, w, axis, high - low + 1000))}
            n = world[cls].count()
            pmap = space.GridMap({axis: tuple(low + (high - low + 1000) * i for i in range(1, w))})
            how = runtime.Balance(axis, w) if kind == "balanced" and w > 1 else None
            runtime.run(world, rules, 1, strategy="local", pmap=pmap)
            got = runtime.run(world, rules, ticks, ticks, "local", pmap, balance=how, measure=True)
            skip = runtime.stable_window(got.tick_seconds, 0.3, 2)
            used = got.tick_seconds[skip:]
            series[w] = runtime.throughput(n, len(used), sum(used))
            out += [(f"{model}, {kind}: agent ticks/s", w, round(series[w])), (f"{model}, {kind}: change place a tick", w, sum(x[cls] for x in got.exchanged) / ticks)]
        out += [(f"{model}, {kind}: share of linear", w, round(x, 2)) for w, x in runtime.scaleup(series).items()]
    return out


def collocation(spark: SparkSession, sf_dir: str, ticks: int = 3) -> list[Row]:
    """Fish: agents exchanged a tick and time, stayers kept in place or not."""
    fish = _held(spark, EXTENTS["fish"](spark, sf_dir))
    pmap, rules = space.initial_partition(fish, ["x"], 8), models.school()
    runtime.run({"fish": fish}, rules, 1, strategy="local", pmap=pmap)
    out: list[Row] = []
    for name, on in (("collocated", True), ("not collocated", False)):
        got = runtime.run({"fish": fish}, rules, ticks, ticks, "local", pmap, collocate=on, measure=True)
        out += [(f"{name}: agents exchanged", t, float(x["fish"])) for t, x in enumerate(got.exchanged)] + [(f"{name}: seconds a tick", 0, round(statistics.median(got.tick_seconds), 3))]
    return out


def storage(spark: SparkSession, sf_dir: str, ticks: int = 4) -> list[Row]:
    """Traffic: agent ticks a second with the world in memory and written a tick."""
    road = _held(spark, EXTENTS["vehicle"](spark, sf_dir))
    n, out = road.count(), []
    for kind in ("memory", "disk"):
        runtime.run({"vehicle": road}, models.traffic(), 1, storage=kind)
        got = runtime.run({"vehicle": road}, models.traffic(), ticks, ticks, storage=kind)
        out.append((kind, ticks, round(runtime.throughput(n, ticks, sum(got.epoch_seconds)))))
    return out


def bounds(spark: SparkSession, sf_dir: str, factors: tuple[int, ...] = (50, 75, 100, 150, 200)) -> list[Row]:
    """Relay: prey whose alarm differs from the right one, by the halo in hundredths
    of the bound, and the copies that halo makes."""
    world = {n: _held(spark, EXTENTS[e](spark, sf_dir)) for n, e in (("predator", "predator"), ("scout", "prey"), ("prey", "prey"))}
    r = 30_000
    rules = invert(models.relay(r))
    pmap = space.initial_partition(world["prey"], ["x", "y"], 4)
    want = tick(world, models.relay(r), 0)["prey"].select("id", F.col("energy").alias("want"))
    out: list[Row] = []
    for f in factors:
        halo = {x: (-r * f // 100, r * f // 100) for x in ("x", "y")}
        got = runtime.closed_ticks(world, rules, 1, pmap, halo)["prey"]
        out += [("wrong alarms", f, float(got.join(want, "id").where("energy <> want").count())), ("copies", f, float(space.replicate(world["prey"], pmap, halo).where("not is_owner").count()))]
    return out


def balance(spark: SparkSession, sf_dir: str, epochs: int = 20, parts: int = 8) -> list[Row]:
    """Fish that swim apart: largest load over mean load (thousandths) and time,
    epoch by epoch, with strips of equal width and with strips that are cut anew
    where that is worth the move."""
    fish = _held(spark, EXTENTS["fish"](spark, sf_dir))
    rules = models.school(speed=400)
    low, high = fish.agg(F.min("y"), F.max("y")).first()
    even = space.GridMap({"y": tuple(low + (high - low) * i // parts for i in range(1, parts))})
    out: list[Row] = []
    for name, how in (("even strips", None), ("balanced", runtime.Balance("y", parts))):
        run = runtime.run({"fish": fish}, rules, epochs, strategy="local", pmap=even, balance=how)
        out.append((f"{name}: switches", 0, float(sum(run.switched))))
        for e, (took, load) in enumerate(zip(run.epoch_seconds, run.loads)):
            out += [(f"{name}: seconds", e, round(took, 3)), (f"{name}: load", e, float(max(load.values()) * 1000 * parts // sum(load.values())))]
    return out


def validation(spark: SparkSession, sf_dir: str, ticks: int = 3) -> list[Row]:
    """Traffic: speed sums a lane, engine against the single-process simulator:
    relative deviation, and agents that differ."""
    road = EXTENTS["vehicle"](spark, sf_dir)
    ours = runtime.run({"vehicle": road}, models.traffic(), ticks).world["vehicle"]
    theirs = traffic_numpy(road, ticks)
    a, b = ([float(r["speed_sum"]) for r in runtime.traffic_stats(x).orderBy("lane").collect()] for x in (ours, theirs))
    return [("deviation", ticks, runtime.rmspe(a, b)), ("differing agents", ticks, float(ours.exceptAll(theirs.select(*ours.columns)).count()))]


def replicas(spark: SparkSession, sf_dir: str, radii: tuple[int, ...] = (75, 150, 300, 600), speeds: tuple[int, ...] = (20, 40, 80)) -> list[Row]:
    """Replicas by visible radius and movers by speed."""
    fish = _held(spark, EXTENTS["fish"](spark, sf_dir))
    pmap = space.initial_partition(fish, ["x", "y"], 4)
    out: list[Row] = [("replicas", r, float(space.replicate(fish, pmap, {"x": (-r, r), "y": (-r, r)}).where("not is_owner").count())) for r in radii]
    for v in speeds:
        after = tick({"fish": fish}, models.school(speed=v), 0)["fish"]
        out.append(("movers", v, float(runtime.movers(fish, after, pmap).agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0])))
    return out


def epochs(spark: SparkSession, sf_dir: str, lengths: tuple[int, ...] = (1, 2, 5, 10), ticks: int = 10) -> list[Row]:
    """Traffic: agent ticks a second by epoch length."""
    road = _held(spark, EXTENTS["vehicle"](spark, sf_dir))
    n = road.count()
    out: list[Row] = []
    runtime.run({"vehicle": road}, models.traffic(), 2)
    for e in lengths:
        run = runtime.run({"vehicle": road}, models.traffic(), ticks, epoch_len=e)
        out.append(("agent ticks/s", e, round(runtime.throughput(n, ticks, sum(run.epoch_seconds)))))
    return out


def scale_up_school(spark: SparkSession, sf_dir: str) -> list[Row]:
    return scale_up(spark, sf_dir, model="school")


SWEEPS = {f.__name__: f for f in (growth, growth_fish, visibility, inversion, scale_up, scale_up_school, balance, validation, bounds, collocation, replicas, epochs, storage)}


def as_table(spark: SparkSession, rows: list[Row]) -> DataFrame:
    return spark.createDataFrame([(s, int(v), float(x)) for s, v, x in rows], "setting string, at bigint, value double")


def main() -> None:
    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "16").config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    for name in sys.argv[2:] or SWEEPS:
        for row in SWEEPS[name](spark, sys.argv[1]):
            print(name, *row, sep="\t", flush=True)


if __name__ == "__main__":
    main()
