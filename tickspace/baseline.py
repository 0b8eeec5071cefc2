"""A single-process traffic simulator on sorted lanes: the baseline that the
engine is compared with.  Same rules as ``models.traffic``, so results must be
equal, agent for agent.  A segment longer than a block is dealt out in blocks that
hold all they can see in the time, each simulated by one process."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .functions.exact import NOISE_MOD

FAR = 1 << 30
COLUMNS = ("id", "lane", "pos", "v", "desired")


def noise_array(ids: np.ndarray, tick: int, stream: int, seed: int = 7) -> np.ndarray:
    """``functions.exact.noise`` for an array of non-negative ids."""
    x = (ids % NOISE_MOD + NOISE_MOD + seed * 7919 + 1) % NOISE_MOD * 48271 % NOISE_MOD
    x = (x + tick * 69621 + stream * 40692 + 13) % NOISE_MOD * 39373 % NOISE_MOD
    return (x + 12345) % NOISE_MOD * 16807 % NOISE_MOD


class _Lane:
    """Vehicles of one lane by (pos, id), with the least speeds of those at one
    position: from a place to the position's end, and up to a place."""

    def __init__(self, key: np.ndarray, pos: np.ndarray, v: np.ndarray):
        order = np.argsort(key)
        self.key, pos, v = key[order], pos[order], v[order]
        self.spots, self.start = np.unique(pos, return_index=True)
        self.end = np.append(self.start[1:], len(pos))
        spot, big = np.repeat(np.arange(len(self.spots)), self.end - self.start), np.int64(1) << 32
        self.onward = np.minimum.accumulate((spot * big + v)[::-1])[::-1] - spot * big
        self.sofar = np.minimum.accumulate(v - spot * big) + spot * big

    def _at(self, pos: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        g = np.searchsorted(self.spots, pos)
        return g, (g < len(self.spots)) & (self.spots[np.minimum(g, len(self.spots) - 1)] == pos)

    def ahead(self, key: np.ndarray, pos: np.ndarray, reach: int) -> tuple[np.ndarray, np.ndarray]:
        """(gap, least speed) of the next position with a vehicle after (pos, id)."""
        gap, speed = np.full(len(pos), FAR), np.zeros(len(pos), np.int64)
        if not len(self.key):
            return gap, speed
        g, here = self._at(pos)
        i = np.searchsorted(self.key, key, "right")
        beside = here & (i < self.end[np.minimum(g, len(self.end) - 1)])
        gap[beside], speed[beside] = 0, self.onward[i[beside]]
        nxt = g + here
        ok = ~beside & (nxt < len(self.spots))
        ok[ok] = self.spots[nxt[ok]] - pos[ok] <= reach
        gap[ok], speed[ok] = self.spots[nxt[ok]] - pos[ok], self.onward[self.start[nxt[ok]]]
        return gap, speed

    def behind(self, key: np.ndarray, pos: np.ndarray, reach: int) -> np.ndarray:
        """Gap to the last vehicle before (pos, id)."""
        gap = np.full(len(pos), FAR)
        if not len(self.key):
            return gap
        g, here = self._at(pos)
        i = np.searchsorted(self.key, key, "left")
        beside = here & (i > self.start[np.minimum(g, len(self.start) - 1)])
        gap[beside] = 0
        ok = ~beside & (g > 0)
        ok[ok] = pos[ok] - self.spots[g[ok] - 1] <= reach
        gap[ok] = pos[ok] - self.spots[g[ok] - 1]
        return gap


def traffic_step(cars: dict[str, np.ndarray], t: int, ahead: int = 1_000, back: int = 500, lanes: int = 5, length: int | None = None) -> dict[str, np.ndarray]:
    id_, lane, pos, v, desired = (cars[c] for c in COLUMNS)
    if not len(id_):
        return cars
    rank = np.searchsorted(np.sort(id_), id_)
    key = pos * len(id_) + rank
    road = {k: _Lane(key[m], pos[m], v[m]) for k in np.unique(lane).tolist() for m in [lane == k]}
    none = _Lane(key[:0], pos[:0], v[:0])
    lead = {k: np.full(len(id_), FAR) for k in (-1, 0, 1)}
    rear = {k: np.full(len(id_), FAR) for k in (-1, 1)}
    lead_v = np.zeros(len(id_), np.int64)
    for own in road:
        m = np.flatnonzero(lane == own)
        for k in (-1, 0, 1):
            there = road.get(own + k, none)
            gap, speed = there.ahead(key[m], pos[m], ahead)
            lead[k][m] = gap
            if k:
                rear[k][m] = there.behind(key[m], pos[m], back)
            else:
                lead_v[m] = speed
    gap = lead[0]
    accel = np.where(gap < 80, -40, np.where(gap < 400, np.clip((lead_v - v) // 2, -20, 20), 10))
    new_v = np.maximum(0, np.minimum(desired, v + accel))
    wants = (gap < 400) & (noise_array(id_, t, 9) % 100 < 60)
    fit = {k: wants & (lead[k] > 100) & (rear[k] > 60) & (lead[k] - gap >= 200) for k in (-1, 1)}
    change = np.where(fit[-1] & (lane > 0), -1, np.where(fit[1] & (lane < lanes - 1), 1, 0))
    step = new_v // 10
    out = {"id": id_, "lane": lane + change, "pos": pos + np.clip(step, 0, 100), "v": new_v, "desired": desired}
    if length is not None:
        stay = pos + step <= length
        out = {c: x[stay] for c, x in out.items()}
    return out


def traffic_numpy(vehicles: DataFrame, ticks: int, block: int = 1_000_000, **rules) -> DataFrame:
    """The vehicles after ``ticks``.  A process computes one block of the road alone,
    from its vehicles and those beyond its ends as far as ``ticks`` ticks can see
    (sight, and a vehicle's longest step of 100 on either side, each tick)."""
    far = ticks * (max(rules.get("ahead", 1_000), rules.get("back", 500)) + 200)
    at = lambda c: F.floor(c / F.lit(float(block))).cast("bigint")
    rows = vehicles.select(*COLUMNS).withColumn("_home", at(F.col("pos"))).withColumn("_block", F.explode(F.sequence(at(F.col("pos") - far), at(F.col("pos") + far))))

    def run(table):
        cars = {c: table.column(c).to_numpy().astype(np.int64) for c in COLUMNS}
        own = cars["id"][table.column("_home").to_numpy() == table.column("_block").to_numpy()]
        for t in range(ticks):
            cars = traffic_step(cars, t, **rules)
        mine = np.isin(cars["id"], own)
        return pa.table({c: cars[c][mine] for c in COLUMNS})

    return rows.groupBy("_block").applyInArrow(run, ", ".join(f"{c} bigint" for c in COLUMNS))
