"""Sums over crowded boxes without making pairs.

A sum is *separable* if a pair adds a value that depends on the offset along one
axis only (or on nothing).  Then the box of a receiver is read off a tile's counts of
agents by place: prefix sums along one axis, weights along the other.  The cost is
that of the receivers times the box's width, whatever the number of pairs; results are
exact integers, the same as those of the pairs.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..plans.agents import REF, Assign, Effect, Loop

Bound = dict[str, tuple[int, int]]
Tables = dict[str, tuple[str, np.ndarray]]

#: from so many estimated pairs on, tiles are counted instead
CROWDED = 100_000_000
#: widest box side that tiles are made for, and products up to which a tile's pairs are compared
WIDEST, FEW = 1 << 11, 1 << 22
_TU, _TV = "_tile_u", "_tile_v"


def separable(loop: Loop, effects: list[tuple[Assign, Effect]]) -> dict[str, tuple[str, str]] | None:
    """effect -> (axis, value as a function of ``d``, the offset b - a), or None."""
    if loop.where != "true" or loop.include_self or not 1 <= len(loop.bound) <= 2 or any(hi - lo > WIDEST for lo, hi in loop.bound.values()):
        return None
    out = {}
    for x, e in effects:
        if e.combinator not in ("sum", "count"):
            return None
        axes, text = set(), x.value
        for axis in loop.bound:  # whole operands only, so that no precedence changes
            for one, two, d in (("b", "a", "d"), ("a", "b", "(0 - d)")):
                text, n = re.subn(rf"(?<=[(,])(\s*){one}\.{axis} - {two}\.{axis}(?=\s*[),])", rf"\g<1>{d}", text)
                axes |= {axis} if n else set()
        if REF.search(text) or len(axes) > 1 or re.search(r"\b(rand|randn|uuid|shuffle|monotonically_increasing_id)\b", text, re.I):
            return None
        out[x.effect] = (next(iter(axes or loop.bound)), "1" if e.combinator == "count" and text.strip() == "1" else text)
        if e.combinator == "count" and text.strip() != "1":
            return None
    return out


def tabulate(spark, loop: Loop, found: dict[str, tuple[str, str]], away: bool) -> Tables | None:
    """The values by offset of the other agent from the receiver; None where they
    are no integers or null somewhere."""
    out = {}
    for effect, (axis, text) in found.items():
        lo, hi = loop.bound[axis]
        rows = spark.range(lo, hi + 1).select(F.col("id").alias("d")).select("d", F.expr(text).alias("v"))
        if not isinstance(rows.schema["v"].dataType, T.IntegralType):
            return None
        got = [r["v"] for r in sorted(rows.collect(), key=lambda r: r["d"])]  # a row an offset
        if any(v is None for v in got):
            return None
        out[effect] = (axis, np.array(got[::-1] if away else got, np.int64))
    return out


def crowded(agents: DataFrame, bound: Bound) -> bool:
    """Are there about ``CROWDED`` pairs or more?  One pass of counts by cell."""
    cells = [F.floor(F.col(x) / F.lit(float(max(1, (hi - lo) // 2)))) for x, (lo, hi) in bound.items()]
    n = agents.groupBy(*cells).agg(F.count("*").cast("double").alias("n")).agg(F.sum(F.col("n") * F.col("n"))).first()[0]
    return 2 ** len(bound) * (n or 0) >= CROWDED


def _tile_sums(at: np.ndarray, seen: np.ndarray, own: np.ndarray, bound: list[tuple[int, int]], weights: list[tuple[int, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    """(pairs, sums) of each receiver; ``own``: it is among ``seen`` itself."""
    (ulo, uhi), (vlo, vhi) = bound
    n, sums = np.zeros(len(at), np.int64), np.zeros((len(at), len(weights)), np.int64)
    if not len(at) or not len(seen):
        return n, sums
    width = [uhi - ulo + 1, vhi - vlo + 1]
    if len(at) * len(seen) <= FEW:
        step = max(1, (1 << 20) // len(seen))
        for k in range(0, len(at), step):
            gap = seen[None, :, :] - at[k : k + step, None, :]
            i, j = np.nonzero((gap[:, :, 0] >= ulo) & (gap[:, :, 0] <= uhi) & (gap[:, :, 1] >= vlo) & (gap[:, :, 1] <= vhi))
            m = len(gap)
            n[k : k + step] = np.bincount(i, minlength=m)
            for c, (axis, w) in enumerate(weights):
                np.add.at(sums[k : k + step, c], i, w[gap[i, j, axis] - bound[axis][0]])
    else:
        first = at.min(0) + [ulo, vlo]
        size = at.max(0) + [uhi, vhi] - first + 1
        ok = ((seen >= first) & (seen < first + size)).all(1)
        spots, many = np.unique((seen[ok, 0] - first[0]) * size[1] + seen[ok, 1] - first[1], return_counts=True)
        places, back = np.unique((at[:, 0] - first[0]) * size[1] + at[:, 1] - first[1], return_inverse=True)
        where = np.stack([places // size[1], places % size[1]], 1)
        total, got = np.zeros(len(places), np.int64), np.zeros((len(places), len(weights)), np.int64)
        exact = all(int(np.abs(w).max(initial=0)) * len(seen) < 1 << 53 for _, w in weights)
        for axis in (0, 1):
            mine = [c for c, (a, _) in enumerate(weights) if a == axis]
            if not mine and axis:
                continue
            other = 1 - axis
            # counts up to a place along the other axis, a row each
            upto = np.zeros((size[other] + 1, size[axis]), np.int32 if len(seen) < 1 << 31 else np.int64)
            s = (spots // size[1], spots % size[1])
            upto[s[other] + 1, s[axis]] = many
            for r in range(1, len(upto)):
                np.add(upto[r], upto[r - 1], out=upto[r])
            w = np.stack([np.ones(width[axis], np.int64), *(weights[c][1] for c in mine)], 1)
            w = w.astype(np.float64) if exact else w
            window = np.lib.stride_tricks.sliding_window_view(upto, width[axis], axis=1)
            low, left = where[:, other] + bound[other][0], where[:, axis] + bound[axis][0]
            for k in range(0, len(places), 256):
                b, x = low[k : k + 256], left[k : k + 256]
                inside = window[b + width[other], x] - window[b, x]
                r = inside.astype(w.dtype) @ w
                total[k : k + 256] = r[:, 0]
                got[k : k + 256, mine] = r[:, 1:]
        n, sums = total[back.ravel()], got[back.ravel()]
    if ulo <= 0 <= uhi and vlo <= 0 <= vhi:
        n = n - own
        for c, (axis, w) in enumerate(weights):
            sums[:, c] -= own * w[-bound[axis][0]]
    return n, sums


def box_sums(receivers: DataFrame, sources: DataFrame, bound: Bound, tables: Tables, keep: list[str], own: str, by: tuple[str, ...] = ()) -> DataFrame:
    """(``keep``, effects) of the receivers with any source in their box.  ``own``:
    condition that a receiver is a source itself; ``by``: columns that keep receivers
    and sources of one part together."""
    axes = list(bound)
    sides = [bound[x] for x in axes] + [(0, 0)] * (2 - len(axes))
    edge = [max(1, hi - lo + 1) for lo, hi in sides]
    put = lambda df, k: [F.col(axes[k]) if k < len(axes) else F.lit(0).cast("bigint")]
    cell = lambda c, k: F.floor(c / F.lit(float(edge[k]))).cast("bigint")
    left = receivers.select(*by, *[c for c in keep if c not in by], *put(receivers, 0), *[c.alias("_v") for c in put(receivers, 1)], F.expr(own).alias("_self"))
    left = left.withColumnRenamed(axes[0], "_u").withColumn(_TU, cell(F.col("_u"), 0)).withColumn(_TV, cell(F.col("_v"), 1))
    right = sources.select(*by, put(sources, 0)[0].alias("_u"), put(sources, 1)[0].alias("_v"))
    for t, c, k in ((_TU, "_u", 0), (_TV, "_v", 1)):
        lo, hi = sides[k]
        right = right.withColumn(t, F.explode(F.sequence(cell(F.col(c) - hi, k), cell(F.col(c) - lo, k))))
    names = list(tables)
    weights = [(axes.index(tables[e][0]), tables[e][1]) for e in names]

    def run(a, b):
        grid = [np.stack([t.column(c).to_numpy() for c in ("_u", "_v")], 1) for t in (a, b)]
        n, sums = _tile_sums(*grid, a.column("_self").to_numpy().astype(np.int64), sides, weights)
        hit = np.flatnonzero(n > 0)
        rest = a.select(keep).take(pa.array(hit))
        return pa.table([*rest.columns, *(pa.array(sums[hit, k]) for k in range(len(names)))], names=[*keep, *names])

    kind = ", ".join([*(f"`{c}` {left.schema[c].dataType.simpleString()}" for c in keep), *(f"`{e}` bigint" for e in names)])
    keys = [*by, _TU, _TV]
    return left.groupBy(*keys).cogroup(right.groupBy(*keys)).applyInArrow(run, kind)
