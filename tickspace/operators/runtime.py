"""Runs of many ticks: epochs, checkpoints, recovery, balancing, collocation.

Within an epoch the world is held in memory (spilled to local disk where it must
be), one copy, in its parts; a tick reads it without any exchange of its own agents
and its plan starts at the held tables, so plans do not grow with the ticks.  At an
epoch's end the world is written to the shared folder: lost executors are made good
from there, by the lineage of one epoch.
"""

from __future__ import annotations

import json
import math
import re
import time
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager
from dataclasses import dataclass, field

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..plans.agents import AgentClass, prepare
from .space import PART, label, place, quantile_splits, replicate, scratch, should_repartition, GridMap
from .tick import IN_PARTS, World, closed_tick, tick

NEXT = "_next"


def checkpoint_dir(spark: SparkSession) -> str:
    """The shared folder of the session.  A folder of this machine only where the
    session names none and runs in this one process; else it is refused."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        base = "/tmp/tickspace-checkpoints"
    return base.rstrip("/")


@dataclass
class RunResult:
    world: World
    tick: int
    epoch_seconds: list[float] = field(default_factory=list)
    path: str = ""
    loads: list[dict[int, int]] = field(default_factory=list)
    maps: list = field(default_factory=list)
    tick_seconds: list[float] = field(default_factory=list)
    exchanged: list[dict[str, int]] = field(default_factory=list)  #: agents that changed place, a tick
    switched: list[bool] = field(default_factory=list)  #: whether an epoch's end re-cut space


def _fs(spark: SparkSession, path: str):
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()), p


def _put(spark: SparkSession, path: str, data: str) -> None:
    """Write a small new file through Hadoop's file systems: whole or not at all."""
    fs, p = _fs(spark, path)
    _, tmp = _fs(spark, path + ".tmp")
    out = fs.create(tmp, True)
    out.write(bytearray(data.encode()))
    out.close()
    if not fs.rename(tmp, p):
        raise OSError(f"cannot put {path}")


def write_checkpoint(world: World, path: str, epoch: int, tick_: int, extra: dict | None = None) -> World:
    """One Parquet folder a class, then the manifest: without it the checkpoint
    does not count.  Every attempt has folders and a manifest of its own, so a
    repeated epoch never touches data that a manifest names.  Returns the world
    read back (lineage cut)."""
    spark = next(iter(world.values())).sparkSession
    out, classes, attempt = {}, {}, uuid.uuid4().hex
    for name, df in world.items():
        where = f"{path}/epoch={epoch}/{name}-{attempt}"
        df.write.parquet(where)
        out[name] = spark.read.schema(df.schema).parquet(where)
        classes[name] = where
    _put(spark, f"{path}/epoch={epoch}/manifest-{attempt}.json", json.dumps({"epoch": epoch, "tick": tick_, "classes": classes, "complete": True} | (extra or {})))
    return out


def resume(spark: SparkSession, path: str, upto: int | None = None) -> tuple[World, int, int] | None:
    """(world, tick, epoch) of the newest complete checkpoint (up to an epoch)."""
    fs, p = _fs(spark, path)
    if not fs.exists(p):
        return None
    epochs = sorted((int(s.getPath().getName().split("=")[1]) for s in fs.listStatus(p) if s.getPath().getName().startswith("epoch=")), reverse=True)
    for e in (e for e in epochs if upto is None or e <= upto):
        found = [s for s in fs.listStatus(_fs(spark, f"{path}/epoch={e}")[1]) if re.fullmatch(r"manifest-\w+\.json", s.getPath().getName())]
        for s in sorted(found, key=lambda s: -s.getModificationTime()):
            m = json.loads(spark.read.text(s.getPath().toString(), wholetext=True).first()[0])
            if m.get("complete") and all(fs.exists(_fs(spark, w)[1]) for w in m["classes"].values()):
                return {n: spark.read.parquet(w) for n, w in m["classes"].items()}, m["tick"], e
    return None


# -- the world in memory -----------------------------------------------------------


@dataclass
class Held:
    """A table kept in the executors' memory; ``df`` is a leaf plan over it."""

    df: DataFrame
    rows: int
    source: DataFrame

    def free(self) -> None:
        self.source.unpersist()


def hold(df: DataFrame) -> Held:
    """Compute ``df`` and keep it, spilling to disk.  The plan handed out begins at
    the kept rows and knows how they are partitioned, but nothing of how they came
    about: plans do not grow.  A lost block is computed anew, by lineage."""
    spark = df.sparkSession
    df.persist(StorageLevel.MEMORY_AND_DISK)
    rows = df.count()
    sql = spark._jvm.org.apache.spark.sql
    kept = sql.classic.Dataset.ofRows(spark._jsparkSession, df._jdf.queryExecution().withCachedData())
    leaf = getattr(getattr(sql.execution, "LogicalRDD$"), "MODULE$").fromDataset(kept.queryExecution().toRdd(), kept, False)
    return Held(DataFrame(sql.classic.Dataset.ofRows(spark._jsparkSession, leaf), spark), rows, df)


@contextmanager
def tick_settings(spark: SparkSession, parts: int) -> Iterator[None]:
    """Settings under which agents that are dealt by part are joined and grouped
    by (part, ...) without another exchange."""
    want = {"spark.sql.adaptive.enabled": "false", "spark.sql.shuffle.partitions": str(parts), "spark.sql.requireAllClusterKeysForCoPartition": "false", "spark.sql.autoBroadcastJoinThreshold": "-1"}
    before = {k: spark.conf.get(k, None) for k in want}
    try:
        for k, v in want.items():
            spark.conf.set(k, v)
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def _moved(staged: Held, parts: int, collocate: bool) -> DataFrame:
    """Agents in the parts they belong to after a tick.  Stayers keep their place,
    movers are exchanged; without collocation all are."""
    stay = staged.df.where(F.col(PART) == F.col(NEXT)).drop(NEXT)
    move = staged.df.where(F.col(PART) != F.col(NEXT)).drop(PART).withColumnRenamed(NEXT, PART)
    if not collocate:
        return staged.df.drop(PART).withColumnRenamed(NEXT, PART).repartition(parts, PART)
    return stay.unionByName(move.repartition(parts, PART))


class Holder:
    """The world of a run, tick by tick, in parts (with a map) or whole."""

    def __init__(self, world: World, classes: dict[str, AgentClass], strategy: str, pmap, collocate: bool, measure: bool):
        self.spark = next(iter(world.values())).sparkSession
        self.classes, self.strategy, self.collocate, self.measure = classes, strategy, collocate, measure
        self.pmap = pmap if strategy in IN_PARTS else None
        self.now = {n: hold(self._placed(df)) for n, df in world.items()}
        self.exchanged: dict[str, int] = {}

    def settings(self):
        return tick_settings(self.spark, self.pmap.parts) if self.pmap is not None else _as_is()

    def _placed(self, df: DataFrame) -> DataFrame:
        if self.pmap is None:
            return df
        with self.settings():
            return place(df, self.pmap)

    def world(self) -> World:
        return {n: h.df.drop(PART) for n, h in self.now.items()}

    def replace(self, new: dict[str, Held]) -> None:
        old, self.now = self.now, new
        for h in old.values():
            h.free()

    def enter(self, spawn: Callable[[World, int], World], t: int) -> None:
        """Agents that enter before a tick join their parts."""
        after = spawn(self.world(), t)
        new = dict(self.now)
        with self.settings():
            for n, df in after.items():
                new[n] = hold(self._placed(df))
        self.replace(new)

    def step(self, t: int) -> None:
        with self.settings():
            after = tick({n: h.df for n, h in self.now.items()}, self.classes, t, self.strategy, self.pmap, {n: h.rows for n, h in self.now.items()})
            if self.pmap is None:
                self.replace({n: hold(df) for n, df in after.items()})
                return
            staged = {n: hold(df.withColumn(NEXT, label(self.spark, self.pmap, self.pmap.part()))) for n, df in after.items()}
            if self.measure:
                self.exchanged = {n: h.df.where(F.col(PART) != F.col(NEXT)).count() if self.collocate else h.rows for n, h in staged.items()}
            self.replace({n: hold(_moved(h, self.pmap.parts, self.collocate)) for n, h in staged.items()})
            for h in staged.values():
                h.free()

    def switch(self, pmap) -> None:
        """Re-cut space: every agent is dealt once by the new map."""
        world, self.pmap = self.world(), pmap
        self.replace({n: hold(self._placed(df)) for n, df in world.items()})

    def free(self) -> None:
        for h in self.now.values():
            h.free()


@contextmanager
def _as_is() -> Iterator[None]:
    yield


@dataclass(frozen=True)
class Balance:
    """Re-cut ``axis`` into ``parts`` strips of about equal load, at the end of an
    epoch, if that is worth the move: the load that the fullest part sheds in
    ``horizon`` ticks against ``cost`` for each agent that moves, plus ``fixed``."""

    axis: str
    parts: int
    horizon: int = 10
    cost: float = 1.0
    fixed: float = 0.0


def review(agents: DataFrame, pmap, how: Balance) -> tuple[bool, GridMap]:
    """(worth it, new map): one pass for the splits, one that counts agents by
    (old part, new part); both give a bounded number of rows."""
    new = GridMap({how.axis: quantile_splits(agents, how.axis, how.parts)})
    flows = agents.groupBy(pmap.part().alias("a"), new.part().alias("b")).agg(F.count("*").alias("n")).collect()
    load = lambda k: [sum(r["n"] for r in flows if r[k] == p) for p in {r[k] for r in flows}] or [0]
    moved = sum(r["n"] for r in flows if r["a"] != r["b"])
    return should_repartition(load("a"), load("b"), moved, how.horizon, how.cost, how.fixed), new


def run(
    world: World,
    classes: dict[str, AgentClass],
    ticks: int,
    epoch_len: int = 1,
    strategy: str = "grid",
    pmap=None,
    path: str | None = None,
    start_tick: int = 0,
    start_epoch: int = 0,
    balance: Balance | None = None,
    spawn: Callable[[World, int], World] | None = None,
    storage: str = "memory",
    collocate: bool = True,
    history: str | None = None,
    measure: bool = False,
    lineage_ticks: int = 64,
) -> RunResult:
    """Ticks in epochs.  The driver acts once an epoch: it writes the world to the
    shared folder (a coordinated checkpoint) and may re-cut space.

    ``storage``: ``memory`` holds the world between ticks, ``disk`` writes and
    reads it at every tick, as a conventional map-reduce system does.  ``spawn``
    adds agents before a tick.  ``history``: a folder that gets the world of every
    tick.  ``measure`` counts the agents that change place (one more job a tick).
    After ``lineage_ticks`` ticks the next epoch starts from the written world, so
    that no lineage grows without end."""
    spark = next(iter(world.values())).sparkSession
    classes = prepare(classes)
    path = path or scratch(spark, "run")
    if strategy in IN_PARTS and pmap is None:
        raise ValueError(f"{strategy} needs a partition map")
    done, epoch, out = start_tick, start_epoch, RunResult(world, start_tick, path=path)
    main, on_disk = next(iter(classes)), storage == "disk"
    if history and start_tick == 0:
        _keep_history(world, history, 0)
    held, since = None, start_tick
    while done < ticks:
        began = time.perf_counter()
        for _ in range(min(epoch_len, ticks - done)):
            started = time.perf_counter()
            if held is None:
                held, since = Holder(world, classes, strategy, pmap, collocate, measure), done
            if spawn is not None:
                held.enter(spawn, done)
            held.step(done)
            done += 1
            if history:
                _keep_history(held.world(), history, done)
            if measure:
                out.exchanged.append(held.exchanged)
            if on_disk:
                world = write_checkpoint(held.world(), f"{path}/ticks", done, done)
                held.free()
                held = None
            out.tick_seconds.append(time.perf_counter() - started)
        epoch += 1
        written = write_checkpoint(world if held is None else held.world(), path, epoch, done)
        out.epoch_seconds.append(time.perf_counter() - began)
        if pmap is not None:
            out.loads.append({r["part"]: r["n"] for r in owned_counts(written[main], pmap).collect()})
        if balance is not None and pmap is not None:
            worth, new = review(written[main], pmap, balance)
            out.switched.append(worth)
            if worth:
                pmap = new
                if held is not None:
                    held.switch(pmap)
        out.maps.append(pmap)
        out.world = world = written
        if held is not None and done - since >= lineage_ticks:
            held.free()
            held = None
    if held is not None:
        held.free()
    out.tick = done
    return out


def _keep_history(world: World, path: str, t: int) -> None:
    for n, df in world.items():
        df.write.mode("overwrite").parquet(f"{path}/{n}/tick={t}")


def history(spark: SparkSession, path: str, name: str) -> DataFrame:
    """All ticks of a class that ``run`` has kept; a filter on ``tick`` prunes."""
    return spark.read.parquet(f"{path}/{name}").withColumn("tick", F.col("tick").cast("bigint"))


def closed_ticks(world: World, classes: dict[str, AgentClass], ticks: int, pmap, halo: dict[str, tuple[int, int]], start_tick: int = 0) -> World:
    """``ticks`` ticks after one exchange: parts get all agents within ``halo`` and
    go on alone; in the end each gives the agents it owns.  Right if the halo is as
    deep as anything can matter in that time (``deep_halo``, ``two_hop_halo``)."""
    classes = prepare(classes)
    spark = next(iter(world.values())).sparkSession
    home = "_home"
    with tick_settings(spark, pmap.parts):
        now = {}
        for n, df in world.items():
            copies = replicate(df, pmap, halo)
            copies = copies.withColumn(PART, label(spark, pmap, F.col("part"))).withColumn(home, label(spark, pmap, F.col("owner_part"))).drop("part", "owner_part", "is_owner")
            now[n] = hold(copies.repartition(pmap.parts, PART))
        for t in range(start_tick, start_tick + ticks):
            after = closed_tick({n: h.df for n, h in now.items()}, classes, t, pmap, (PART, home))
            old, now = now, {n: hold(df) for n, df in after.items()}
            for h in old.values():
                h.free()
        out = write_checkpoint({n: h.df.where(F.col(PART) == F.col(home)).drop(PART, home) for n, h in now.items()}, scratch(spark, "closed"), 1, start_tick + ticks)
        for h in now.values():
            h.free()
    return out


def deep_halo(classes: dict[str, AgentClass], ticks: int) -> dict[str, tuple[int, int]]:
    """How far, for an axis, an agent may be and still matter within ``ticks``:
    sight and twice the movement of each tick (its own and that of what it sees)."""
    out: dict[str, int] = {}
    for c in classes.values():
        for loop in c.loops:
            for axis, b in loop.bound.items():
                reach = max(max(map(abs, x.states[axis].reach or (0,))) for x in classes.values() if axis in x.states)
                if any(x.states[axis].update is not None and x.states[axis].reach is None for x in classes.values() if axis in x.states):
                    raise ValueError(f"{axis} moves without a bound")
                out[axis] = max(out.get(axis, 0), ticks * (max(map(abs, b)) + 2 * reach))
    return {axis: (-far, far) for axis, far in out.items()}


def owned_counts(agents: DataFrame, pmap: GridMap) -> DataFrame:
    return agents.groupBy(pmap.part().alias("part")).agg(F.count("*").alias("n"))


def imbalance(counts: DataFrame, parts: int) -> DataFrame:
    """Largest load over mean load, in thousandths."""
    return counts.agg(F.floor(F.max("n") * 1000 * parts / F.sum("n")).cast("bigint").alias("permille"))


def movers(before: DataFrame, after: DataFrame, pmap: GridMap) -> DataFrame:
    """(from, to, n) of agents whose part has changed."""
    a = before.select("id", pmap.part().alias("from"))
    b = after.select("id", pmap.part().alias("to"))
    return a.join(b, "id").where("`from` <> `to`").groupBy("from", "to").agg(F.count("*").alias("n"))


# -- generic iterated map-reduce ---------------------------------------------


def iterate_mapreduce(kv: DataFrame, mapper: Callable, reducer: Callable, rounds: int, base: str | None = None) -> DataFrame:
    """kv: columns k, v.  mapper: (k, v) -> array of structs (k, v); reducer:
    (k, sorted array of v) -> array of structs (k, v).  One shuffle a round."""
    spark = kv.sparkSession
    base = base or scratch(spark, "mr")
    for i in range(rounds):
        mapped = kv.select(F.explode(mapper(F.col("k"), F.col("v"))).alias("m")).select("m.k", "m.v")
        grouped = mapped.groupBy("k").agg(F.array_sort(F.collect_list("v")).alias("v"))
        kv = grouped.select(F.explode(reducer(F.col("k"), F.col("v"))).alias("r")).select("r.k", "r.v")
        if i + 1 < rounds:
            kv.write.mode("overwrite").parquet(f"{base}/round={i}")
            kv = spark.read.parquet(f"{base}/round={i}")
    return kv


# -- costs and measures --------------------------------------------------------


def optimal_interval(cost: float, mtbf: float, second_order: bool = False) -> float:
    """Run time between checkpoints that minimises the expected total."""
    first = math.sqrt(2 * cost * mtbf)
    if not second_order or cost >= 2 * mtbf:
        return first if not second_order else mtbf
    x = cost / (2 * mtbf)
    return first * (1 + math.sqrt(x) / 3 + x / 9) - cost


def expected_runtime(work: float, interval: float, cost: float, mtbf: float, restart: float = 0.0) -> float:
    """With exponential failures: segments of interval + cost, each re-run until
    one passes without a failure."""
    return work / interval * (mtbf + restart) * (math.exp((interval + cost) / mtbf) - 1)


def throughput(agents: int, ticks: int, seconds: float) -> float:
    return agents * ticks / seconds


def stable_window(tick_seconds: list[float], tolerance: float = 0.1, width: int = 3) -> int:
    """Ticks to discard until ``width`` in a row differ by the tolerance only."""
    for i in range(len(tick_seconds) - width + 1):
        w = tick_seconds[i : i + width]
        if max(w) - min(w) <= tolerance * max(w):
            return i
    return max(0, len(tick_seconds) - width)


def loglog_slope(sizes: list[float], seconds: list[float]) -> float:
    xs, ys = [math.log(x) for x in sizes], [math.log(y) for y in seconds]
    mx, my = sum(xs) / len(xs), sum(ys) / len(ys)
    return sum((x - mx) * (y - my) for x, y in zip(xs, ys)) / sum((x - mx) ** 2 for x in xs)


def scaleup(series: dict[int, float]) -> dict[int, float]:
    """workers -> throughput, as shares of linear growth."""
    return {w: t / (w * series[1]) for w, t in series.items()}


def rmspe(a: list[float], b: list[float]) -> float:
    return math.sqrt(sum(((x - y) / x) ** 2 for x, y in zip(a, b) if x) / max(1, sum(1 for x in a if x)))


def should_invert(message_bytes: int, extra_replica_bytes: int) -> bool:
    """Inversion saves the messages and pays with a wider halo (two-hop case)."""
    return message_bytes > extra_replica_bytes


def exchanges(df: DataFrame) -> list[str]:
    """The exchanges of the executed plan's static form, reused ones once; not
    those by which a cached table was made."""
    out, inside = [], None
    for line in df._jdf.queryExecution().executedPlan().toString().split("\n"):
        depth = len(line) - len(line.lstrip(" :+-"))
        if inside is not None and depth > inside:
            continue
        inside = depth if "InMemoryRelation" in line else None
        if m := re.search(r"(?<!Reused)Exchange ((?:hash|range)partitioning\(.*?\d\)|SinglePartition)", line):
            out.append(m[1])
    return out


def exchange_count(df: DataFrame) -> int:
    return len(exchanges(df))


def shuffle_bytes(spark: SparkSession, action: Callable[[], object]) -> int:
    """Bytes that the stages of ``action`` write to their shuffles, as the
    session's own status store has them."""
    store = spark._jsc.sc().statusStore()
    none = spark._jvm.java.util.ArrayList()

    def stages():
        every = store.stageList(none, False, False, spark.sparkContext._gateway.new_array(spark._jvm.double, 0), none)
        return {(s.stageId(), s.attemptId()): s.shuffleWriteBytes() for s in spark._jvm.scala.jdk.javaapi.CollectionConverters.asJava(every)}

    before = stages()
    action()
    spark._jsc.sc().listenerBus().waitUntilEmpty(30_000)
    return sum(n for k, n in stages().items() if k not in before)


def same_world(a: DataFrame, b: DataFrame) -> bool:
    return a.exceptAll(b.select(*a.columns)).isEmpty() and b.select(*a.columns).exceptAll(a).isEmpty()


def traffic_stats(vehicles: DataFrame, length: int | None = None) -> DataFrame:
    """Per lane: vehicles, sum of speeds; with the road's ``length`` also density
    (vehicles a km) and flow (vehicles an hour past a place), both in thousandths;
    lengths in decimetres, speeds in decimetres a second."""
    out = vehicles.groupBy("lane").agg(F.count("*").alias("n"), F.sum("v").alias("speed_sum"))
    if length is None:
        return out
    return out.withColumn("density", F.expr(f"n * 10000000 div {length}")).withColumn("flow", F.expr(f"speed_sum * 3600000 div {length}"))


def school_stats(fish: DataFrame) -> DataFrame:
    """Per class (informed of one or the other direction, the rest): size, sums of
    places and headings, and the polarisation, |sum of headings| over the sum of
    their lengths in thousandths."""
    kind = F.least(F.col("informed"), F.lit(2))
    length = F.sum(F.floor(F.sqrt((F.col("vx") * F.col("vx") + F.col("vy") * F.col("vy")).cast("double"))))
    out = fish.groupBy(kind.alias("class")).agg(F.count("*").alias("n"), *[F.sum(c).alias(f"sum_{c}") for c in ("x", "y", "vx", "vy")], length.alias("lengths"))
    whole = F.sqrt((F.col("sum_vx") * F.col("sum_vx") + F.col("sum_vy") * F.col("sum_vy")).cast("double"))
    return out.withColumn("polarisation", F.when(F.col("lengths") > 0, F.floor(whole * 1000 / F.col("lengths")))).drop("lengths")


def school_split(fish: DataFrame, axis: str = "x") -> DataFrame:
    """Distance of the two informed classes' mean places along an axis."""
    mean = lambda k: F.floor(F.avg(F.when(F.col("informed") == k, F.col(axis))))
    return fish.agg((mean(1) - mean(0)).alias("split"))


def prefix_load(hist: DataFrame) -> DataFrame:
    return hist.withColumn("running", F.sum("load").over(Window.orderBy("bin").rowsBetween(Window.unboundedPreceding, 0)))
