"""Visible pairs: the spatial self-join by several strategies, one result.

Every strategy gives the pairs (a_*, b_*) with b inside a's box.  ``columns``
prunes what each side carries.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .folds import Fold
from .space import PART, GridMap, _labels, borders, place, replicate

Bound = dict[str, tuple[int, int]]


def _side(df: DataFrame, p: str) -> DataFrame:
    return df.select(*[F.col(c).alias(f"{p}_{c}") for c in df.columns])


def _inside(bound: Bound):
    out = F.lit(True)
    for axis, (lo, hi) in bound.items():
        out = out & (F.col(f"b_{axis}") - F.col(f"a_{axis}")).between(lo, hi)
    return out


def nested_loop(a: DataFrame, b: DataFrame, bound: Bound, fold: Fold | None = None, rows: int = 50_000) -> DataFrame:
    """No index (baseline): every pair is tested.  With a ``fold``, blocks of
    ``rows`` readers meet blocks of seen rows and hand out the readers (a_*) that see
    any and their sums, not the pairs."""
    left, right = _side(a, "a"), _side(b, "b")
    if fold is None:
        return left.join(right, _inside(bound))
    mine, run = left.columns, _folding(_all_batches, bound, fold, left.columns)
    left, right = _placed(left, "a", bound), _placed(right, "b", bound)
    n, m = (max(1, -(-df.count() // rows)) for df in (a, b))
    of = lambda df, k: F.pmod(F.xxhash64(*df.columns), F.lit(k)).cast("int")
    spread = lambda k: F.explode(F.sequence(F.lit(0), F.lit(k - 1)))
    # a reader that is among the seen rows is so in one of its blocks
    left = fold.readers(left.select("*", of(left, n).alias("_i"), of(left, m).alias("_mine")).withColumn("_j", spread(m)).withColumn("_self", F.col("_j") == F.col("_mine")))
    right = fold.seen(right.withColumn("_j", of(right, m)), [*(f"b_{x}" for x in bound), "_j"]).withColumn("_i", spread(n))
    left, right = (df.withColumn("_block", F.col("_i") * m + F.col("_j")).drop("_i", "_j", "_mine") for df in (left, right))
    if n * m <= 1024:  # a block a partition
        names = F.array(*map(F.lit, _labels(a.sparkSession, n * m)))
        left, right = (df.withColumn("_block", F.element_at(names, F.col("_block") + 1)).repartition(n * m, "_block") for df in (left, right))
    kind = ", ".join([*(f"`{c}` {left.schema[c].dataType.simpleString()}" for c in mine), *(f"`{c}` bigint" for c in ["_seen", *fold.names])])
    got = left.groupBy("_block").cogroup(right.groupBy("_block")).applyInArrow(run, kind)
    every = got.groupBy(*mine).agg(*[F.sum(c).alias(c) for c in ["_seen", *fold.names]])
    return every.where("_seen > 0").drop("_seen")


def _placed(side: DataFrame, p: str, bound: Bound) -> DataFrame:
    """Without rows that have no place: they see nobody and nobody sees them."""
    for x in bound:
        side = side.where(F.col(f"{p}_{x}").isNotNull())
    return side


def _folding(find, bound: Bound, fold: Fold, keep: list[str]):
    """The Arrow function of a block: readers' ``keep``, agents seen, sums."""
    low, high = (np.array([bound[x][k] for x in bound], np.int64) for k in (0, 1))

    def run(a, b):
        at = [np.stack([t.column(f"{p}_{x}").to_numpy() for x in bound], 1).astype(np.int64) for t, p in ((a, "a"), (b, "b"))]
        own = [a.column(f"_w{k}").to_numpy() for k in range(len(fold.weights))] if fold.alone else []
        self = a.column("_self").to_numpy().astype(np.int64)
        n, got = fold.run(find, *at, low, high, self, own, [b.column(f"_w{k}").to_numpy() for k in range(len(fold.weights))], b.column("_many").to_numpy() if fold.many else None)
        return pa.table([*a.select(keep).columns, pa.array(n), *map(pa.array, got)], names=[*keep, "_seen", *fold.names])

    return run


def grid(a: DataFrame, b: DataFrame, bound: Bound, cell: dict[str, int] | None = None) -> DataFrame:
    """Readers are copied to the cells of their box and meet the seen agents'
    cells in an equi-join, which splits hot cells; d dimensions."""
    size = {x: max(1, (cell or {}).get(x, max(abs(lo), abs(hi), 1))) for x, (lo, hi) in bound.items()}
    left, right = _side(a, "a"), _side(b, "b")
    floor = lambda c, w: F.floor(c / F.lit(float(w))).cast("bigint")
    for x, (lo, hi) in bound.items():
        left = left.withColumn(f"cell_{x}", F.explode(F.sequence(floor(F.col(f"a_{x}") + lo, size[x]), floor(F.col(f"a_{x}") + hi, size[x]))))
        right = right.withColumn(f"cell_{x}", floor(F.col(f"b_{x}"), size[x]))
    keys = [f"cell_{x}" for x in bound]
    return left.join(right, keys).where(_inside(bound)).drop(*keys)


def two_level(a: DataFrame, b: DataFrame, bound: Bound, pmap: GridMap, cell: dict[str, int] | None = None) -> DataFrame:
    """Owned agents and replicas meet by part over the network, by cell inside
    the task; the pairs keep ``a_part`` and ``b_owner_part``."""
    own = a.withColumn("part", pmap.part())
    copies = replicate(b, pmap, bound).drop("is_owner")
    size = {x: max(1, (cell or {}).get(x, max(abs(lo), abs(hi), 1))) for x, (lo, hi) in bound.items()}
    left, right = _side(own, "a"), _side(copies, "b")
    floor = lambda c, w: F.floor(c / F.lit(float(w))).cast("bigint")
    for x, (lo, hi) in bound.items():
        left = left.withColumn(f"cell_{x}", F.explode(F.sequence(floor(F.col(f"a_{x}") + lo, size[x]), floor(F.col(f"a_{x}") + hi, size[x]))))
        right = right.withColumn(f"cell_{x}", floor(F.col(f"b_{x}"), size[x]))
    keys = [f"cell_{x}" for x in bound]
    both = [left["a_part"] == right["b_part"], *(left[k] == right[k] for k in keys)]
    return left.join(right, both).where(_inside(bound)).drop(*keys, "b_part")


def broadcast_small(a: DataFrame, b: DataFrame, bound: Bound, max_rows: int = 50_000) -> DataFrame:
    """One small class goes to every task if it is proven small, else grid."""
    if b.limit(max_rows + 1).count() > max_rows:
        return grid(a, b, bound)
    return _side(a, "a").join(F.broadcast(_side(b, "b")), _inside(bound))


#: pairs that a kernel tests at a time
BATCH = 1 << 20


def _kd_batches(ax: np.ndarray, bx: np.ndarray, low: np.ndarray, high: np.ndarray, whole=None, leaf: int = 32):
    """Batches (i, j) with bx[j] - ax[i] in [low, high], by a median tree over bx: at
    every node all readers whose box meets the node's box go on together.  Nodes wholly
    within a reader's box go to ``whole`` (readers, rows), where it is given."""
    if not len(ax) or not len(bx):
        return
    todo = [(np.arange(len(bx)), np.arange(len(ax)), 0)]
    d = bx.shape[1]
    while todo:
        rows, readers, axis = todo.pop()
        box, at = bx[rows], ax[readers]
        first, last = box.min(0), box.max(0)
        meets = np.ones(len(readers), bool)
        for x in range(d):
            meets &= (at[:, x] >= first[x] - high[x]) & (at[:, x] <= last[x] - low[x])
        if whole is not None:
            inside = np.ones(len(readers), bool)
            for x in range(d):
                inside &= (at[:, x] >= last[x] - high[x]) & (at[:, x] <= first[x] - low[x])
            if inside.any():
                whole(readers[inside], rows)
                meets &= ~inside
        readers = readers[meets]
        if not len(readers):
            continue
        if len(rows) <= leaf:
            step = BATCH // leaf
            for k in range(0, len(readers), step):
                some = readers[k : k + step]
                ok = True
                for x in range(d):
                    gap = box[None, :, x] - ax[some, x][:, None]
                    ok &= (gap >= low[x]) & (gap <= high[x])
                at = np.flatnonzero(ok)
                i = at // len(rows)
                yield some[i], rows[at - i * len(rows)]
            continue
        half = len(rows) // 2
        order = np.argpartition(box[:, axis], half)
        todo += [(rows[order[:half]], readers, (axis + 1) % d), (rows[order[half:]], readers, (axis + 1) % d)]


def _sweep_batches(ax: np.ndarray, bx: np.ndarray, low: np.ndarray, high: np.ndarray, whole=None):
    """Batches as of ``_kd_batches``, by a sorted sweep along the first axis."""
    order = np.argsort(bx[:, 0], kind="stable")
    line = np.ascontiguousarray(bx[order].T)
    lo, hi = np.searchsorted(line[0], ax[:, 0] + low[0], "left"), np.searchsorted(line[0], ax[:, 0] + high[0], "right")
    n = np.maximum(hi - lo, 0)
    upto, k = np.cumsum(n), 0
    while k < len(ax):
        end = max(k + 1, int(np.searchsorted(upto, (upto[k - 1] if k else 0) + BATCH, "right")))
        i = np.repeat(np.arange(k, end), n[k:end])
        j = np.arange(len(i)) + np.repeat(lo[k:end] - (upto[k:end] - n[k:end] - (upto[k - 1] if k else 0)), n[k:end])
        for x in range(1, bx.shape[1]):
            gap = line[x, j] - ax[i, x]
            ok = np.flatnonzero((gap >= low[x]) & (gap <= high[x]))
            i, j = i[ok], j[ok]
        yield i, order[j]
        k = end


def _all_batches(ax: np.ndarray, bx: np.ndarray, low: np.ndarray, high: np.ndarray, whole=None):
    """Batches as of ``_kd_batches``, without an index (baseline): all pairs are
    tested, by the places' upper bits (a byte an axis) and, where those fit, exactly."""
    if not len(ax) or not len(bx):
        return
    tests = []
    for x in range(bx.shape[1]):
        ends = [int(f(v)) for f in (np.min, np.max) for v in (bx[:, x], ax[:, x] + low[x])]
        first, last = min(ends), max(ends)
        cut = max(0, (last - first).bit_length() - 8)
        wide = (int(high[x] - low[x]) >> cut) + 1
        if wide < 255:
            tests.append((((ax[:, x] + low[x] - first) >> cut).astype(np.uint8), ((bx[:, x] - first) >> cut).astype(np.uint8), np.uint8(wide)))
    side, mine, its = (128, 1 << 13), np.ascontiguousarray(ax.T), np.ascontiguousarray(bx.T)
    gap, fits, ok = np.empty(side, np.uint8), np.empty(side, bool), np.ones(side, bool)
    for k in range(0, len(ax), side[0]):
        for m in range(0, len(bx), side[1]):
            rows = min(side[1], len(bx) - m)
            here = (slice(min(side[0], len(ax) - k)), slice(rows))
            for x, (qa, qb, wide) in enumerate(tests):
                np.subtract(qb[None, m : m + side[1]], qa[k : k + side[0], None], out=gap[here])
                np.less_equal(gap[here], wide, out=(fits if x else ok)[here])
                if x:
                    np.logical_and(ok[here], fits[here], out=ok[here])
            hits = _set_places(ok[here])
            i = hits // rows
            j = hits - i * rows + m
            i += k
            for x in range(bx.shape[1]):
                far = its[x].take(j) - mine[x].take(i)
                hit = np.flatnonzero((far >= low[x]) & (far <= high[x]))
                i, j = i.take(hit), j.take(hit)
            yield i, j


def _set_places(ok: np.ndarray) -> np.ndarray:
    """``np.flatnonzero`` of few set bytes, eight at a time."""
    flat = np.ascontiguousarray(ok).reshape(-1)
    if len(flat) < 1 << 12:
        return np.flatnonzero(flat)
    upto = len(flat) // 8 * 8
    eight = flat[:upto].view(np.uint64)
    words = _set_places(eight != 0)
    at = np.flatnonzero(eight[words].view(bool))
    found = words[at >> 3] * 8 + (at & 7)
    return found if upto == len(flat) else np.concatenate([found, upto + np.flatnonzero(flat[upto:])])


def _pairs_of(batches):
    """A kernel that hands out all pairs at once."""

    def find(ax, bx, low, high):
        found = [(np.zeros(0, np.int64), np.zeros(0, np.int64)), *batches(ax, bx, low, high)]
        return tuple(np.concatenate(side) for side in zip(*found))

    return find


def _nearest_pairs(ax: np.ndarray, bx: np.ndarray, low: np.ndarray, high: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of ``_sweep_pairs``, those nearest along the first axis, one way and the
    other, for each offset of the further axes; all agents of such a place."""
    if not len(ax) or not len(bx):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    lanes, lane = np.unique(bx[:, 1:], axis=0, return_inverse=True)
    order = np.lexsort((bx[:, 0], lane.ravel()))
    of, line = lane.ravel()[order], bx[order, 0]
    new = np.append(True, (of[1:] != of[:-1]) | (line[1:] != line[:-1]))
    first = np.flatnonzero(new)
    last = np.append(first[1:], len(order))
    lane_at = np.searchsorted(of[first], np.arange(len(lanes) + 1))
    out_i, out_j = [], []
    for k in range(len(lanes)):
        near = np.flatnonzero(((lanes[k] - ax[:, 1:] >= low[1:]) & (lanes[k] - ax[:, 1:] <= high[1:])).all(1))
        spots = line[first[lane_at[k] : lane_at[k + 1]]]
        at = np.searchsorted(spots, ax[near, 0], "left")
        here = (at < len(spots)) & (spots[np.minimum(at, len(spots) - 1)] == ax[near, 0])
        for g, ok in ((at, here), (at + here, np.ones(len(near), bool)), (at - 1, np.ones(len(near), bool))):
            ok = ok & (g >= 0) & (g < len(spots))
            gap = spots[g[ok]] - ax[near[ok], 0]
            fits = (gap >= low[0]) & (gap <= high[0])
            spot, reader = lane_at[k] + g[ok][fits], near[ok][fits]
            n = last[spot] - first[spot]
            out_i.append(np.repeat(reader, n))
            out_j.append(order[np.repeat(first[spot], n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)])
    return np.concatenate(out_i), np.concatenate(out_j)


BATCHES = {"all": _all_batches, "kdtree": _kd_batches, "sweep": _sweep_batches}
KERNELS = {**{how: _pairs_of(batches) for how, batches in BATCHES.items()}, "nearest": _nearest_pairs}


def pairs_in_parts(own: DataFrame, seen: DataFrame, bound: Bound, how: str = "cells") -> DataFrame:
    """Pairs (a_*, b_*) of placed readers and of the agents in their part; both
    sides hold column ``PART``.  ``cells``: an equi-join that needs no exchange
    beyond the placing; else a kernel on each part's Arrow tables."""
    left, right = _side(own, "a"), _side(seen, "b")
    mine, its = f"a_{PART}", f"b_{PART}"
    if how == "cells":
        floor = lambda c, w: F.floor(c / F.lit(float(w))).cast("bigint")
        for x, (lo, hi) in bound.items():
            w = max(1, abs(lo), abs(hi))
            left = left.withColumn(f"ca_{x}", F.explode(F.sequence(floor(F.col(f"a_{x}") + lo, w), floor(F.col(f"a_{x}") + hi, w))))
            right = right.withColumn(f"cb_{x}", floor(F.col(f"b_{x}"), w))
        both = [F.col(mine) == F.col(its), *(F.col(f"ca_{x}") == F.col(f"cb_{x}") for x in bound)]
        return left.join(right, both).where(_inside(bound)).drop(its, *(f"c{s}_{x}" for s in "ab" for x in bound))
    find, axes = KERNELS[how], list(bound)
    low, high = (np.array([bound[x][k] for x in axes]) for k in (0, 1))

    def run(key, a, b):
        i, j = find(*(np.stack([t.column(f"{p}_{x}").to_numpy() for x in axes], 1) for t, p in ((a, "a"), (b, "b"))), low, high)
        a, b = a.drop_columns(blocks).take(pa.array(i)), b.drop_columns([its, *blocks]).take(pa.array(j))
        return pa.table([*a.columns, *b.columns], names=[*a.column_names, *b.column_names])

    kind = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in [*left.schema, *right.drop(its).schema])
    left, right, blocks = _blocks(left, right, bound, 16)
    return left.groupBy(mine, *blocks).cogroup(right.groupBy(its, *blocks)).applyInArrow(run, kind)


def _blocks(left: DataFrame, right: DataFrame, bound: Bound, boxes: int) -> tuple[DataFrame, DataFrame, list[str]]:
    """Blocks of a part, so many boxes wide, so that no call holds a crowded part."""
    for x, (lo, hi) in bound.items():
        block = lambda c: F.floor(c / F.lit(float(boxes) * (hi - lo + 1))).cast("bigint")  # noqa: B023, E731
        left = left.withColumn(f"_in_{x}", block(F.col(f"a_{x}")))
        right = right.withColumn(f"_in_{x}", F.explode(F.sequence(block(F.col(f"b_{x}") - hi), block(F.col(f"b_{x}") - lo))))
    return left, right, [f"_in_{x}" for x in bound]


def _boxes(agents: DataFrame, bound: Bound, rows: int = 20_000) -> int:
    """How many boxes wide blocks of about so many rows are: 2 to 16."""
    cells = [F.floor(F.col(x) / F.lit(2.0 * (hi - lo + 1))) for x, (lo, hi) in bound.items()]
    n = agents.groupBy(*cells).agg(F.count("*").alias("n")).agg(F.avg("n")).first()[0] or 1
    return max(k for k in (2, 4, 8, 16) if k == 2 or (k // 2) ** len(bound) * n <= rows)


def fold_in_parts(own: DataFrame, seen: DataFrame, bound: Bound, how: str, fold: Fold) -> DataFrame:
    """The readers (a_*) of ``pairs_in_parts`` that see any, with the sums of their
    pairs, which a kernel meets in batches."""
    left, right = _placed(_side(own, "a"), "a", bound), _placed(_side(seen, "b"), "b", bound)
    run, keep = _folding(BATCHES[how], bound, fold, left.columns), left.columns
    kind = ", ".join([*(f"`{c}` {left.schema[c].dataType.simpleString()}" for c in keep), *(f"`{c}` bigint" for c in ["_seen", *fold.names])])
    left, right = fold.readers(left.withColumn("_self", F.lit(True))), fold.seen(right, [f"b_{PART}", *(f"b_{x}" for x in bound)])
    left, right, blocks = _blocks(left, right, bound, _boxes(own, bound))
    got = left.groupBy(f"a_{PART}", *blocks).cogroup(right.groupBy(f"b_{PART}", *blocks)).applyInArrow(run, kind)
    return got.where("_seen > 0").drop("_seen")


def kd_tree(a: DataFrame, b: DataFrame, bound: Bound, pmap, how: str = "kdtree", fold: Fold | None = None) -> DataFrame:
    """A median tree (or another of ``KERNELS``) inside each part, over owned
    agents and replicas; ``parts_for`` sizes the parts so that one fits a task.
    With a ``fold``, the readers and the sums of their pairs."""
    own = place(a, pmap)
    seen = place(b, pmap)
    seen = seen.withColumn("_owner", F.lit(None).cast("int")).unionByName(borders(seen, pmap, bound))
    if fold is not None:
        return fold_in_parts(own, seen, bound, how, fold).drop(f"a_{PART}")
    found = pairs_in_parts(own, seen, bound, how).withColumnsRenamed({f"a_{PART}": "a_part", "b__owner": "b_owner_part"})
    return found.withColumn("b_owner_part", F.coalesce("b_owner_part", "a_part"))


def parts_for(rows: int, rows_a_part: int = 200_000) -> int:
    """How many parts keep each within what one task holds."""
    return max(1, -(-rows // rows_a_part))


def _blocked(agents: DataFrame, by: str, axis: str, low: int, high: int, block: int) -> DataFrame:
    """Each row in its block of ``axis`` (``_own``) and in the others from which
    an offset in [low, high] reaches it."""
    cell = lambda c: F.floor(c / F.lit(float(block))).cast("bigint")
    at = agents.withColumn("_home", cell(F.col(axis)))
    spread = F.sequence(cell(F.col(axis) - high), cell(F.col(axis) - low))
    return at.withColumn("_block", F.explode(F.array_union(F.array("_home"), spread))).withColumn("_own", F.col("_block") == F.col("_home"))


def nearest_ahead(agents: DataFrame, by: str, axis: str, m: int = 1, block: int = 100_000) -> DataFrame:
    """The m next agents along ``axis`` with the same ``by``: (id, rank, other,
    gap).  Windows hold a block of the axis and the first m agents beyond it,
    which come from the blocks' own first m: no task holds a lane."""
    rows = agents.select("id", F.col(by).alias("_by"), F.col(axis).alias("_at"), F.floor(F.col(axis) / F.lit(float(block))).alias("_block"))
    k = F.row_number().over(Window.partitionBy("_by", "_block").orderBy("_at", "id"))
    first = rows.withColumn("k", k).where(F.col("k") <= m).groupBy("_by", "_block").agg(F.array_sort(F.collect_list(F.struct("_at", "id"))).alias("f"))
    w = Window.partitionBy("_by").orderBy("_block")  # a row a block
    beyond = F.slice(F.flatten(F.collect_list("f").over(w.rowsBetween(1, m))), 1, m)
    after = first.withColumn("b", beyond).select("_by", "_block", F.explode("b").alias("x")).select("x.id", "_by", "x._at", "_block", F.lit(False).alias("_own"))
    every = rows.withColumn("_own", F.lit(True)).unionByName(after)
    here = Window.partitionBy("_by", "_block").orderBy("_at", "id")
    near = F.collect_list(F.struct("id", "_at")).over(here.rowsBetween(1, m))
    out = every.withColumn("near", near).where("_own").select("id", "_at", F.posexplode("near").alias("rank", "x"))
    return out.select("id", (F.col("rank") + 1).alias("rank"), F.col("x.id").alias("other"), (F.col("x._at") - F.col("_at")).alias("gap"))


def _first_ids(agents: DataFrame, x: str, y: str, m: int) -> DataFrame:
    """(x, y, ids): the ``m`` smallest ids of each place, in order."""
    k = F.row_number().over(Window.partitionBy(x, y).orderBy("id"))
    return agents.select("id", x, y).withColumn("k", k).where(F.col("k") <= m).groupBy(x, y).agg(F.array_sort(F.collect_list("id")).alias("ids"))


def nearest_others(agents: DataFrame, x: str, y: str, r: int, m: int) -> DataFrame:
    """(id, rank, other): the m nearest others within r on both axes, ties by id.
    Places of more than m agents answer by themselves; the rest look at pairs of
    places."""
    places = _first_ids(agents, x, y, m + 1)
    lonely = places.where(F.size("ids") <= m).select(x, y)
    d2 = f"(b_{x} - a_{x}) * (b_{x} - a_{x}) + (b_{y} - a_{y}) * (b_{y} - a_{y})"
    every = places.where(F.size("ids") > m)
    for q in sorted({q for q in (r // 64, r // 8, r) if q > 0} | {r}):  # first those that find enough nearby
        p = grid(lonely, places, {x: (-q, q), y: (-q, q)}).select(F.col(f"a_{x}").alias(x), F.col(f"a_{y}").alias(y), F.expr(d2).alias("d2"), F.explode("b_ids").alias("id"))
        p = p if q == r else p.where(F.col("d2") <= q * q)
        first = p.withColumn("k", F.row_number().over(Window.partitionBy(x, y).orderBy("d2", "id"))).where(F.col("k") <= m + 1)
        found = first.groupBy(x, y).agg(F.transform(F.array_sort(F.collect_list(F.struct("d2", "id"))), lambda o: o["id"]).alias("ids"))
        if q < r:
            found = found.where(F.size("ids") > m)
            lonely = lonely.join(found, [x, y], "left_anti")
        every = every.unionByName(found)
    return agents.select("id", x, y).join(every, [x, y]).select("id", F.posexplode(F.slice(F.array_except("ids", F.array("id")), 1, m)).alias("k", "other")).select("id", (F.col("k") + 1).alias("rank"), "other")


def sweep_counts(agents: DataFrame, by: str, axis: str, low: int, high: int, block: int | None = None) -> DataFrame:
    """(id, n, sum_id) over others of the same ``by`` within [low, high] along
    ``axis``: a sorted sweep that makes no pairs, over blocks of the axis with
    the rows beyond their borders that are within reach."""
    block = block or 64 * max(1, high - low)
    w = Window.partitionBy(by, "_block").orderBy(axis).rangeBetween(low, high)
    inside = F.lit(int(low <= 0 <= high))
    rows = _blocked(agents.select("id", by, axis), by, axis, low, high, block)
    swept = rows.select("id", "_own", (F.count("*").over(w) - inside).alias("n"), F.sum("id").over(w).alias("s"))
    return swept.where("_own").select("id", "n", (F.coalesce("s", F.lit(0)) - inside * F.col("id")).alias("sum_id"))


def range_join(points: DataFrame, at: str, ranges: DataFrame, low: str, high: str, cell: int) -> DataFrame:
    """Points and the ranges [low, high] that hold them, by an equi-join on
    cells of the axis; a range is copied to the cells it meets."""
    floor = lambda c: F.floor(c / F.lit(float(cell))).cast("bigint")
    left = points.withColumn("_cell", floor(F.col(at)))
    right = ranges.where(F.col(low) <= F.col(high)).withColumn("_cell", F.explode(F.sequence(floor(F.col(low)), floor(F.col(high)))))
    return left.join(right, "_cell").where(F.col(at).between(F.col(low), F.col(high))).drop("_cell")


def choose_join(n_readers: int, n_seen: int, bound: Bound, small: int = 2_000) -> str:
    """The strategy by estimated cost: broadcast of a tiny class, nested loops
    where both are tiny or unbounded, else the grid."""
    if not bound or n_readers * n_seen <= small * small // 4:
        return "nested"
    return "broadcast" if n_seen <= small else "grid"


def resolve_refs(agents: DataFrame, ref: str, bound: Bound) -> DataFrame:
    """(id, ref, resolved): the reference, null once its target is out of sight."""
    left = _side(agents, "a")
    right = agents.select(F.col("id").alias("b_id"), *[F.col(x).alias(f"b_{x}") for x in bound])
    return left.join(right, (F.col(f"a_{ref}") == F.col("b_id")) & _inside(bound), "left").select(F.col("a_id").alias("id"), F.col(f"a_{ref}").alias("ref"), F.col("b_id").alias("resolved"))
