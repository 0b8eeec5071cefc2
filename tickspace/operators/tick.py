"""One tick: query phase (pairs, contributions, combination), update phase.

Strategies differ in how pairs are found and how often data is exchanged:

* ``semantic``: loops over whole extents (nested loops), the reference meaning;
* ``grid``: cells over the whole space;
* ``auto``: nested loops, a broadcast of one class or cells, by the classes' sizes;
* with a partition map, ``local``, ``nonlocal`` (cells inside a part), ``kdtree``,
  ``sweep``, ``nearest`` (kernels inside a part): agents stay in their parts and
  only copies for other parts' sight are exchanged.  Effects for the looping
  agent need no more; effects for seen agents are combined at the copies first and
  then, after a second exchange, at their owners.  (Pairs of the three kernels
  come back without a partitioning, so their effects are exchanged once more.)
"""

from __future__ import annotations

import re
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.agents import COMBINATORS, REF, AgentClass, Loop, prepare
from . import dense, folds, visible
from .space import PART, borders, place

World = dict[str, DataFrame]
IN_PARTS = ("local", "nonlocal", *visible.KERNELS)


def _columns(expr: str) -> str:
    return REF.sub(lambda m: f"{m[1]}_{m[2]}", expr)


def _needed(loop: Loop, side: str) -> list[str]:
    text = " ".join([loop.where, *(a.value for a in loop.assigns)])
    return list(dict.fromkeys(["id", *loop.bound, *(f for s, f in REF.findall(text) if s == side)]))


def pairs(loop: Loop, readers: DataFrame, seen: DataFrame, same: bool, strategy: str, sizes: tuple[int, int] | None = None) -> DataFrame:
    a, b = readers.select(*_needed(loop, "a")), seen.select(*_needed(loop, "b"))
    how = "grid"
    if strategy == "auto" and sizes is not None:
        how = visible.choose_join(*sizes, loop.bound)
    if not loop.bound or strategy == "semantic" or how == "nested":
        out = visible.nested_loop(a, b, loop.bound)
    elif how == "broadcast":
        out = visible.broadcast_small(a, b, loop.bound)
    else:
        out = visible.grid(a, b, loop.bound)
    return _refined(out, loop, same)


def _refined(out: DataFrame, loop: Loop, same: bool) -> DataFrame:
    if same and not loop.include_self:
        out = out.where("a_id <> b_id")
    return out.where(_columns(loop.where)) if loop.where != "true" else out


def _messages(p: DataFrame, assigns, keys: dict[str, str], effects) -> DataFrame:
    """Partial values by receiver; ``keys``: column of the pairs -> its new name."""
    values = [COMBINATORS[effects[x.effect].combinator].partial(F.expr(_columns(x.value))).alias(x.effect) for x in assigns]
    return p.groupBy(*[F.col(c).alias(n) for c, n in keys.items()]).agg(*values)


def _tables(loop: Loop, name: str, classes: dict[str, AgentClass], agents: DataFrame) -> tuple[dict, dict] | None:
    """Values by offset of a loop over its own crowded class whose sums need no
    pairs (``dense``): those for the looping agents and those for the seen ones."""
    found = [dense.separable(loop, [(x, classes[loop.seen if away else name].effects[x.effect]) for x in loop.assigns if x.to_seen == away]) for away in (False, True)]
    if name != loop.seen or None in found or not dense.crowded(agents.select(*loop.bound), loop.bound):
        return None
    tables = [dense.tabulate(agents.sparkSession, loop, f, away) for away, f in zip((False, True), found)]
    return None if None in tables else (tables[0], tables[1])


def _mirrored(bound: dict[str, tuple[int, int]]) -> dict[str, tuple[int, int]]:
    return {axis: (-hi, -lo) for axis, (lo, hi) in bound.items()}


#: combinators that need of equal contributions only their number, or not even that
_BY_KIND = {"sum", "count", "min", "max", "any", "every", "bit_or", "bit_and", "set", "hll"}


def _alike(loop: Loop, name: str, classes: dict[str, AgentClass]) -> list[str] | None:
    """The columns by which agents of a loop over their own class are alike (a
    *kind*): what the loop reads of either.  None where it matters who they are."""
    cols = list(dict.fromkeys(c for side in "ab" for c in _needed(loop, side) if c != "id"))
    reads_id = "id" in (f for _, f in REF.findall(" ".join([loop.where, *(a.value for a in loop.assigns)])))
    effects = [classes[loop.seen if x.to_seen else name].effects[x.effect].combinator for x in loop.assigns]
    if name != loop.seen or reads_id or not set(effects) <= _BY_KIND or not set(cols) <= set(classes[name].states):
        return None
    return cols


def _kinds(agents: DataFrame, cols: list[str], by: tuple[str, ...] = ()) -> DataFrame:
    return agents.groupBy(*by, *cols).agg(F.count("*").alias("_n"))


def _kind_messages(p: DataFrame, loop: Loop, cols: list[str], agents: DataFrame, c: AgentClass, by: tuple[str, ...] = ()) -> list[DataFrame]:
    """Partial values by agent from pairs of kinds: a pair counts as often as the
    other kind has agents, without the agent itself."""
    p = p.where(_columns(loop.where)) if loop.where != "true" else p
    equal = F.lit(not loop.include_self)
    for x in cols:
        equal = equal & F.col(f"a_{x}").eqNullSafe(F.col(f"b_{x}"))
    if by:
        equal = equal & F.col("b__owner").isNull()
    out = []
    for side, other in (("a", "b"), ("b", "a")):
        some = [x for x in loop.assigns if x.to_seen == (side == "b")]
        if not some:
            continue
        many = p.withColumn("_w", F.col(f"{other}__n") - equal.cast("bigint")).where("_w > 0")
        values = []
        for x in some:
            k, v = COMBINATORS[c.effects[x.effect].combinator], F.expr(_columns(x.value))
            times = {"sum": F.sum(v * F.col("_w")), "count": F.sum(F.when(v.isNotNull(), F.col("_w")))}.get(k.name)
            values.append((k.partial(v) if times is None else times).alias(x.effect))
        got = many.groupBy(*[F.col(f"a_{b}").alias(f"_k_{b}") for b in by], *[F.col(f"{side}_{x}").alias(f"_k_{x}") for x in cols]).agg(*values)
        out.append(_of_kinds(got, [x.effect for x in some], cols, agents, by))
    return out


def _of_kinds(got: DataFrame, effects: list[str], cols: list[str], agents: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """A kind's values (its columns named ``_k_``) for each of its agents."""
    on = [F.col(b) == F.col(f"_k_{b}") for b in by] + [F.col(x).eqNullSafe(F.col(f"_k_{x}")) for x in cols]
    return agents.select(*by, "id", *cols).join(got, on).select(*by, "id", *effects)


def _folded(loop: Loop, cols: list[str], kinds: DataFrame, agents: DataFrame, c: AgentClass, meet: Callable, by: tuple[str, ...] = ()) -> list[DataFrame] | None:
    """As ``_kind_messages``, of sums that need no pairs handed out (``folds``), or
    None.  ``meet``: bound, fold -> readers with their sums."""
    out = []
    for away in (False, True):
        some = [(x, c.effects[x.effect]) for x in loop.assigns if x.to_seen == away]
        if not some:
            continue
        fold = folds.plan(kinds, loop, some, away, "b__n")
        if fold is None:
            return None
        got = meet(_mirrored(loop.bound) if away else loop.bound, fold)
        got = got.select(*[F.col(f"a_{x}").alias(f"_k_{x}") for x in (*by, *cols)], *fold.names)
        out.append(_of_kinds(got, fold.names, cols, agents, by))
    return out


def _hinted(loop: Loop, name: str) -> bool:
    same = len(set(loop.bound.values())) == 1 and len(loop.bound) == 2 and all(lo == -hi for lo, hi in loop.bound.values())
    return name == loop.seen and same and loop.where == "true" and not loop.include_self and all((x.closest or x.ref) and not x.to_seen for x in loop.assigns)


def _hinted_messages(loop: Loop, agents: DataFrame, c: AgentClass) -> list[DataFrame]:
    """Of a loop that wants the agent referred to and the closest one only."""
    (x, y), far = loop.bound, next(iter(loop.bound.values()))[1]
    mine, its = visible._side(agents.select(*dict.fromkeys([*_needed(loop, "a"), *(r.ref for r in loop.assigns if r.ref)])), "a"), visible._side(agents.select(*_needed(loop, "b")), "b")
    out = []
    for r in loop.assigns:
        if r.ref:
            p = mine.join(its, (F.col(f"a_{r.ref}") == F.col("b_id")) & visible._inside(loop.bound)).where("a_id <> b_id")
        else:
            near = visible.nearest_others(agents, x, y, far, 1).select(F.col("id").alias("a_id"), F.col("other").alias("b_id"))
            p = near.join(mine, "a_id").join(its, "b_id")
        out.append(_messages(p, [r], {"a_id": "id"}, c.effects))
    return out


def query_phase(world: World, classes: dict[str, AgentClass], strategy: str = "grid", pmap=None, sizes: dict[str, int] | None = None) -> dict[str, list[DataFrame]]:
    """Per class the partial effect tables (id, effects...)."""
    if strategy in IN_PARTS and pmap is not None:
        world = {n: place(df, pmap) for n, df in world.items()}
        return _effects_in_parts(world, classes, pmap, strategy)
    out: dict[str, list[DataFrame]] = {n: [] for n in classes}
    context = dict(world)
    stages = sorted({x.stage for c in classes.values() for x in c.loops})
    for stage in stages:
        for name, c in classes.items():
            for loop in (x for x in c.loops if x.stage == stage):
                seen = (context if loop.context else world)[loop.seen]
                tables = _tables(loop, name, classes, world[name]) if strategy in ("grid", "auto") else None
                if tables is not None:
                    for values, bound in zip(tables, (loop.bound, _mirrored(loop.bound))):
                        if values:
                            out[name].append(dense.box_sums(world[name], world[name], bound, values, ["id"], "true"))
                    continue
                if strategy == "grid" and _hinted(loop, name):
                    out[name] += _hinted_messages(loop, world[name], c)
                    continue
                alike = _alike(loop, name, classes) if strategy == "semantic" else None
                if alike is not None:
                    kinds = _kinds(world[name], alike)
                    folded = _folded(loop, alike, kinds, world[name], c, lambda bound, fold: visible.nested_loop(kinds, kinds, bound, fold))  # noqa: B023
                    out[name] += folded if folded is not None else _kind_messages(visible.nested_loop(kinds, kinds, loop.bound), loop, alike, world[name], c)
                    continue
                p = pairs(loop, context[name], seen, name == loop.seen, strategy, (sizes[name], sizes[loop.seen]) if sizes else None)
                mine = [x for x in loop.assigns if not x.to_seen]
                away = [x for x in loop.assigns if x.to_seen]
                if mine:
                    out[name].append(_messages(p, mine, {"a_id": "id"}, c.effects))
                if away:
                    out[loop.seen].append(_messages(p, away, {"b_id": "id"}, classes[loop.seen].effects))
        if stage != stages[-1]:  # later loops may read what this stage has gathered
            context = {n: attach(world[n], c, out[n]) for n, c in classes.items()}
    return out


def _effects_in_parts(world: World, classes: dict[str, AgentClass], pmap, strategy: str, closed: bool = False) -> dict[str, list[DataFrame]]:
    """As ``query_phase``, of placed agents; the tables have ``PART`` too.

    ``closed``: every part holds all that its agents see (``runtime.closed_ticks``):
    nothing is exchanged, and effects for seen agents stay with the part's copy."""
    how = strategy if strategy in visible.KERNELS else "cells"
    out: dict[str, list[DataFrame]] = {n: [] for n in classes}
    context = dict(world)
    stages = sorted({x.stage for c in classes.values() for x in c.loops})
    for stage in stages:
        for name, c in classes.items():
            for loop in (x for x in c.loops if x.stage == stage):
                if not loop.bound:
                    raise ValueError(f"{name}: a loop without a bound cannot run in parts")
                a = context[name].select(PART, *_needed(loop, "a"))
                b = (context if loop.context else world)[loop.seen].select(PART, *_needed(loop, "b"))
                # of the part's own agents the owner is told after the join: a second
                # name of the part would hide how the rows are dealt
                seen = b.withColumn("_owner", F.lit(None).cast("int"))
                if not closed:
                    seen = seen.unionByName(borders(b, pmap, loop.bound))
                tables = _tables(loop, name, classes, world[name]) if how == "cells" else None
                if tables is not None and closed:
                    for values, bound in zip(tables, (loop.bound, _mirrored(loop.bound))):
                        if values:
                            out[name].append(dense.box_sums(a, b, bound, values, [PART, "id"], "true", (PART,)))
                    continue
                if tables is not None:
                    if tables[0]:
                        out[name].append(dense.box_sums(a, seen, loop.bound, tables[0], [PART, "id"], "true", (PART,)))
                    if tables[1]:
                        sent = dense.box_sums(seen, a, _mirrored(loop.bound), tables[1], [PART, "_owner", "id"], "_owner is null", (PART,))
                        sent = sent.withColumn(PART, F.coalesce("_owner", PART)).drop("_owner")
                        out[name].append(sent.repartition(pmap.parts, PART).withColumn("_more", F.lit(True)))
                    continue
                find = "sweep" if how == "nearest" and not loop.nearest else how
                alike = _alike(loop, name, classes) if how != "cells" and not any(x.to_seen for x in loop.assigns) else None
                if alike is not None:
                    kinds = _kinds(world[name], alike, (PART,))
                    seen = kinds.withColumn("_owner", F.lit(None).cast("int")).unionByName(borders(kinds, pmap, loop.bound))
                    folded = _folded(loop, alike, kinds, world[name], c, lambda bound, fold: visible.fold_in_parts(kinds, seen, bound, find, fold), (PART,)) if find in visible.BATCHES else None  # noqa: B023
                    out[name] += folded if folded is not None else _kind_messages(visible.pairs_in_parts(kinds, seen, loop.bound, find), loop, alike, world[name], c, (PART,))
                    continue
                p = _refined(visible.pairs_in_parts(a, seen, loop.bound, find), loop, name == loop.seen)
                mine = [x for x in loop.assigns if not x.to_seen]
                away = [x for x in loop.assigns if x.to_seen]
                here = f"a_{PART}"
                p = p.withColumn("b__owner", F.coalesce("b__owner", here))
                if mine:
                    out[name].append(_messages(p, mine, {here: PART, "a_id": "id"}, c.effects))
                if away and closed:
                    out[loop.seen].append(_messages(p, away, {here: PART, "b_id": "id"}, classes[loop.seen].effects))
                elif away:  # first at the copies, then with what other parts send
                    sent = _messages(p, away, {here: "_from", "b__owner": PART, "b_id": "id"}, classes[loop.seen].effects)
                    out[loop.seen].append(sent.drop("_from").repartition(pmap.parts, PART).withColumn("_more", F.lit(True)))
        if stage != stages[-1]:
            context = {n: attach(world[n], c, out[n]) for n, c in classes.items()}
    return out


def combine(c: AgentClass, partials: list[DataFrame]) -> DataFrame | None:
    """Merge of partials at the owner.  A single table in which every agent has
    one row is merged already."""
    if not partials:
        return None
    keys = [k for k in (PART, "id") if k in partials[0].columns]
    if len(partials) == 1 and "_more" not in partials[0].columns:
        return partials[0]
    have = {e: next((p.schema[e].dataType for p in partials if e in p.columns), None) for e in c.effects}
    wide = [p.select(*keys, *[(F.col(e) if e in p.columns else F.lit(None).cast(t)).alias(e) for e, t in have.items() if t is not None]) for p in partials]
    every = reduce(DataFrame.unionByName, wide)
    return every.groupBy(*keys).agg(*[COMBINATORS[c.effects[e].combinator].merge(F.col(e)).alias(e) for e, t in have.items() if t is not None])


def attach(agents: DataFrame, c: AgentClass, partials: list[DataFrame]) -> DataFrame:
    """Agents with their effects; identities where nothing was assigned."""
    own = agents.drop(*[e for e in c.effects if e in agents.columns])
    got = combine(c, partials)
    if got is not None:
        keys = [k for k in (PART, "id") if k in got.columns and k in own.columns]
        own = own.join(got if PART in keys else got.drop(PART), keys, "left")
    for e, x in c.effects.items():
        if e not in own.columns:
            own = own.withColumn(e, F.lit(x.default).cast("bigint") if not isinstance(x.default, bool) else F.lit(x.default))
        elif x.default is not None:
            own = own.withColumn(e, F.coalesce(e, F.lit(x.default)))
    return own


def update_phase(full: DataFrame, c: AgentClass, t: int, keep: tuple[str, ...] = ()) -> DataFrame:
    """Every rule reads the old states and the effects; one projection a let.
    ``keep``: columns of the engine's own that stay."""
    for name, rule in c.lets:
        value = F.expr(rule.replace("{t}", str(t)))
        # a generator of one row keeps the optimiser from writing the value out
        # at each use, which would make nested rules grow exponentially
        full = full.select("*", F.explode(F.array(value)).alias(name)) if len(c.lets) > 3 else full.withColumn(name, value)
    if c.die:
        full = full.where(f"NOT ({c.die})")
    out = [F.col("id"), *map(F.col, keep)]
    for s, x in c.states.items():
        value = F.col(s) if x.update is None else F.expr(x.update.replace("{t}", str(t)))
        if x.reach is not None:
            value = F.greatest(F.col(s) + x.reach[0], F.least(F.col(s) + x.reach[1], value))
        out.append(value.cast(full.schema[s].dataType).alias(s))
    if c.born is None:
        return full.select(*out)
    given = {s: F.expr(v.replace("{t}", str(t))).cast(full.schema[s].dataType).alias(s) for s, v in c.born.states.items()}
    child = [(F.col("id") + c.born.gap * (t + 1)).alias("id"), *map(F.col, keep), *[given.get(s, x) for s, x in zip(c.states, out[1 + len(keep) :])]]
    me, it = F.struct(*out), F.struct(*child)
    both = full.select(F.explode(F.when(F.expr(c.born.when.replace("{t}", str(t))), F.array(me, it)).otherwise(F.array(me))).alias("r"))
    return both.select("r.*")


def tick(world: World, classes: dict[str, AgentClass], t: int, strategy: str = "grid", pmap=None, sizes: dict[str, int] | None = None) -> World:
    """The world after tick ``t``.  In parts, agents come back where they were
    before it (column ``PART`` where the input had it)."""
    classes = prepare(classes)
    if strategy in IN_PARTS and pmap is not None:
        stay = tuple(PART for df in world.values() if PART in df.columns)[:1]
        world = {n: place(df, pmap) for n, df in world.items()}
        partials = _effects_in_parts(world, classes, pmap, strategy)
    else:
        stay, partials = (), query_phase(world, classes, strategy, pmap, sizes)
    return {n: update_phase(attach(world[n], c, partials[n]), c, t, stay) for n, c in classes.items()}


def closed_tick(world: World, classes: dict[str, AgentClass], t: int, pmap, keep: tuple[str, ...]) -> World:
    """A tick in which no part looks beyond what it holds."""
    partials = _effects_in_parts(world, classes, pmap, "local", closed=True)
    return {n: update_phase(attach(world[n], c, partials[n]), c, t, keep) for n, c in classes.items()}


# -- the same meaning as plain SQL, for checking against other engines ------


def _sql_effect(effects, x) -> str:
    return COMBINATORS[effects[x.effect].combinator].sql.format(x.value)


def _literal(v) -> str:
    return "NULL" if v is None else str(v).upper() if isinstance(v, bool) else f"CAST({v} AS BIGINT)"


def naive_sql(classes: dict[str, AgentClass], extents: dict[str, str], ticks: int, select: str, spawn: dict[str, Callable[[int], str]] | None = None) -> str:
    """WITH-query that runs the classes by nested loops; ``select`` reads
    <class>_<ticks>.  An independent lowering: no cells, parts or replicas.
    ``spawn``: for a class the rows that enter before a tick."""
    enters = lambda n, t: f" UNION ALL {spawn[n](t)}" if spawn and n in spawn and t < ticks else ""
    ctes = [f"{n}_0 AS MATERIALIZED ({q}{enters(n, 0)})" for n, q in extents.items()]
    for t in range(ticks):
        stages = sorted({x.stage for c in classes.values() for x in c.loops}) or [0]
        source = {n: f"{n}_{t}" for n in classes}
        for stage in stages:
            parts: dict[str, list[tuple[str, str]]] = {n: [] for n in classes}
            for n, c in classes.items():
                for k, loop in enumerate(c.loops):
                    if loop.stage != stage:
                        continue
                    on = [f"b.{x} - a.{x} BETWEEN {lo} AND {hi}" for x, (lo, hi) in loop.bound.items()]
                    if n == loop.seen and not loop.include_self:
                        on.append("a.id <> b.id")
                    on.append(loop.where)
                    for side, to, effects in (("a", n, c.effects), ("b", loop.seen, classes[loop.seen].effects)):
                        some = [x for x in loop.assigns if x.to_seen == (side == "b")]
                        if some:
                            cte = f"m_{n}_{t}_{k}_{side}"
                            ctes.append(f"{cte} AS MATERIALIZED (SELECT {side}.id AS id, {', '.join(f'{_sql_effect(effects, x)} AS {x.effect}' for x in some)} FROM {source[n]} a JOIN {source[loop.seen] if loop.context else f'{loop.seen}_{t}'} b ON {' AND '.join(on)} GROUP BY {side}.id)")
                            parts[to] += [(x.effect, cte) for x in some]
            for n, c in classes.items():
                cols = [f"s.{x}" for x in c.columns()]
                if stage != stages[0]:
                    done = {e for x in c.loops if x.stage < stage for e in [y.effect for y in x.assigns if not y.to_seen]}
                else:
                    done = set()
                joins = "".join(f" LEFT JOIN {m} ON {m}.id = s.id" for m in dict.fromkeys(m for _, m in parts[n]))
                for e, x in c.effects.items():
                    own = [m for f, m in parts[n] if f == e]
                    if e in done and not own:
                        cols.append(f"s.{e}")
                    elif len(own) == 1:
                        cols.append(f"coalesce({own[0]}.{e}, {_literal(x.default)}) AS {e}" if x.default is not None else f"{own[0]}.{e} AS {e}")
                    elif own:
                        op = {"sum": " + ", "count": " + "}.get(x.combinator)
                        pieces = [f"coalesce({m}.{e}, 0)" for m in own] if op else [f"{m}.{e}" for m in own]
                        value = op.join(pieces) if op else f"{'least' if x.combinator == 'min' else 'greatest'}({', '.join(pieces)})"
                        cols.append(f"coalesce({value}, {_literal(x.default)}) AS {e}" if x.default is not None else f"{value} AS {e}")
                    else:
                        cols.append(f"{_literal(x.default)} AS {e}")
                ctes.append(f"e_{n}_{t}_{stage} AS MATERIALIZED (SELECT {', '.join(cols)} FROM {source[n]} s{joins})")
                source[n] = f"e_{n}_{t}_{stage}"
        for n, c in classes.items():
            inner = f"SELECT * FROM {source[n]}"
            for name, rule in c.lets:
                inner = f"SELECT *, {rule.replace('{t}', str(t))} AS {name} FROM ({inner})"
            cols, child = ["id"], [f"id + {c.born.gap * (t + 1)} AS id"] if c.born else []
            for s, x in c.states.items():
                value = s if x.update is None else x.update.replace("{t}", str(t))
                if x.reach is not None:
                    value = f"greatest({s} + {x.reach[0]}, least({s} + {x.reach[1]}, {value}))"
                cols.append(f"CAST({value} AS BIGINT) AS {s}" if x.update is not None else s)
                if c.born:
                    child.append(f"CAST({c.born.states[s].replace('{t}', str(t))} AS BIGINT) AS {s}" if s in c.born.states else cols[-1])
            where = f" WHERE NOT ({c.die})" if c.die else ""
            more = f" UNION ALL SELECT {', '.join(child)} FROM ({inner}) WHERE {f'NOT ({c.die}) AND ' if c.die else ''}({c.born.when.replace('{t}', str(t))})" if c.born else ""
            ctes.append(f"{n}_{t + 1} AS MATERIALIZED (SELECT {', '.join(cols)} FROM ({inner}){where}{more}{enters(n, t + 1)})")
    return "WITH " + ",\n".join(ctes) + "\n" + re.sub(r"\{T\}", str(ticks), select)
