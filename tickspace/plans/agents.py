"""Agent classes: states, effects with combinators, visibility, update rules.

Rules are SQL expressions.  In a loop ``a.f`` is the looping agent's state and
``b.f`` the seen one's; update rules name the agent's own states and effects.
Static checks run before any job (``check``).
"""

from __future__ import annotations

import re
from dataclasses import dataclass, field, replace

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Combinator:
    """Decomposable and order-independent: partial over contributions, merge
    over partials; ``identity`` stands where nothing was assigned."""

    name: str
    partial: callable
    merge: callable
    identity: object = None
    sql: str = ""


def _times(values: Column) -> Column:
    """Exact product of an agent's few partial values; overflow raises."""
    return F.when(F.size(values) > 0, F.aggregate(values, F.lit(1).cast("bigint"), lambda a, x: a * x))


COMBINATORS = {
    c.name: c
    for c in (
        Combinator("sum", F.sum, F.sum, 0, "CAST(sum({}) AS BIGINT)"),
        Combinator("count", lambda c: F.count(c), F.sum, 0, "count({})"),
        Combinator("min", F.min, F.min, None, "min({})"),
        Combinator("max", F.max, F.max, None, "max({})"),
        Combinator("any", F.bool_or, F.bool_or, False, "bool_or({})"),
        Combinator("every", F.bool_and, F.bool_and, True, "bool_and({})"),
        Combinator("bit_or", F.bit_or, F.bit_or, 0, "bit_or({})"),
        Combinator("bit_and", F.bit_and, F.bit_and, -1, "bit_and({})"),
        Combinator("bit_xor", F.bit_xor, F.bit_xor, 0, "bit_xor({})"),
        Combinator("product", lambda c: _times(F.collect_list(c)), lambda c: _times(F.collect_list(c)), 1, "CAST(product({}) AS BIGINT)"),
        Combinator("hll", F.hll_sketch_agg, F.hll_union_agg, None, "count(DISTINCT {})"),
        Combinator("set", lambda c: F.array_sort(F.collect_set(c)), lambda c: F.array_sort(F.array_distinct(F.flatten(F.collect_list(c)))), None, "list_sort(list_distinct(list({})))"),
    )
}
_ORDERED = {"first", "last", "any_value", "append", "list"}


def register_combinator(combinator: Combinator, samples: list | None = None, apply: callable = None) -> None:
    """Add a combinator.  ``apply`` (two values -> one) and ``samples`` check
    that it is commutative, associative and has the stated identity."""
    if combinator.name in _ORDERED:
        raise ValueError(f"NO_COMBINATOR: {combinator.name} depends on the order")
    if apply is not None:
        for x in samples or ():
            if combinator.identity is not None and apply(x, combinator.identity) != x:
                raise ValueError(f"{combinator.name}: wrong identity")
            for y in samples:
                if apply(x, y) != apply(y, x):
                    raise ValueError(f"{combinator.name}: not commutative")
                for z in samples:
                    if apply(apply(x, y), z) != apply(x, apply(y, z)):
                        raise ValueError(f"{combinator.name}: not associative")
    COMBINATORS[combinator.name] = combinator


def top_m(m: int) -> Combinator:
    """The m smallest structs; ties fall to the next field."""
    cut = lambda c: F.slice(F.array_sort(c), 1, m)
    return Combinator(f"top{m}", lambda c: cut(F.collect_list(c)), lambda c: cut(F.flatten(F.collect_list(c))))


def histogram(edges: list[int]) -> Combinator:
    """Counts of the values below, between and from the edges on, as an array."""
    low, high = [None, *edges], [*edges, None]

    def partial(c):
        c = F.expr(c) if isinstance(c, str) else c
        inside = [(F.lit(True) if a is None else c >= a) & (F.lit(True) if b is None else c < b) for a, b in zip(low, high)]
        return F.array(*[F.count_if(x) for x in inside])

    return Combinator("histogram_" + "_".join(map(str, edges)).replace("-", "m"), partial, lambda c: F.array(*[F.sum(F.element_at(c, i + 1)) for i in range(len(low))]))


@dataclass(frozen=True)
class State:
    update: str | None = None  #: None: unchanged
    reach: tuple[int, int] | None = None  #: the update is cropped to old + [lo, hi]


@dataclass(frozen=True)
class Effect:
    combinator: str = "sum"
    identity: object = None  #: instead of the combinator's own

    @property
    def default(self):
        return COMBINATORS[self.combinator].identity if self.identity is None else self.identity


@dataclass(frozen=True)
class Assign:
    effect: str
    value: str
    to_seen: bool = False  #: non-local: the receiver is the seen agent
    ref: str = ""  #: only the agent whose id is this state of the looping one gives a value
    closest: bool = False  #: only the closest agent (of equal ones that of the least id) matters


@dataclass(frozen=True)
class Loop:
    """For each agent of ``seen`` within ``bound`` (axis -> interval relative to
    the looping agent); ``where`` refines the box (a disc, a lane)."""

    seen: str
    bound: dict[str, tuple[int, int]]
    assigns: tuple[Assign, ...]
    where: str = "true"
    include_self: bool = False
    stage: int = 0  #: effects of earlier stages may be read as a.<effect>
    nearest: bool = False  #: only the agents nearest along the first axis matter
    context: bool = False  #: b.<effect> of earlier stages is read (made by ``invert``)


@dataclass(frozen=True)
class Born:
    """A child for each agent that fulfils ``when`` after its update: the states
    not given are the parent's new ones; the id is the parent's plus ``gap`` times
    the number of the tick after this one."""

    when: str
    states: dict[str, str] = field(default_factory=dict)
    gap: int = 1_000_000_000


@dataclass(frozen=True)
class AgentClass:
    name: str
    states: dict[str, State]
    effects: dict[str, Effect] = field(default_factory=dict)
    loops: tuple[Loop, ...] = ()
    lets: tuple[tuple[str, str], ...] = ()  #: named intermediate values of the update
    die: str | None = None
    born: Born | None = None

    def columns(self) -> list[str]:
        return ["id", *self.states]


REF = re.compile(r"\b([ab])\.(\w+)")


def swap(expr: str) -> str:
    return REF.sub(lambda m: f"{'b' if m[1] == 'a' else 'a'}.{m[2]}", expr)


def check(world: dict[str, AgentClass]) -> list[str]:
    """Diagnostics, empty if the classes are sound."""
    out = []
    for c in world.values():
        for both in set(c.states) & set(c.effects):
            out.append(f"UNTAGGED_FIELD: {c.name}.{both} is a state and an effect")
        for e, x in c.effects.items():
            if x.combinator not in COMBINATORS:
                out.append(f"NO_COMBINATOR: {c.name}.{e}")
        for s, x in c.states.items():
            if x.reach and x.reach[0] > x.reach[1]:
                out.append(f"BAD_BOUND: {c.name}.{s}")
            if x.update and REF.search(x.update):
                out.append(f"FOREIGN_READ_IN_UPDATE: {c.name}.{s}")
        for loop in c.loops:
            seen = world.get(loop.seen)
            if seen is None:
                out.append(f"UNKNOWN_CLASS: {loop.seen}")
                continue
            early = {a.effect for x in c.loops if x.stage < loop.stage for a in x.assigns if not a.to_seen}
            for axis, (lo, hi) in loop.bound.items():
                if lo > hi:
                    out.append(f"BAD_BOUND: {c.name} {axis}")
                if axis not in c.states or axis not in seen.states:
                    out.append(f"BAD_BOUND: {axis} is no state")
            for a in loop.assigns:
                receiver = seen if a.to_seen else c
                if a.effect in receiver.states:
                    out.append(f"STATE_WRITE_IN_QUERY: {receiver.name}.{a.effect}")
                elif a.effect not in receiver.effects:
                    out.append(f"UNKNOWN_FIELD: {receiver.name}.{a.effect}")
            for text in [loop.where, *(a.value for a in loop.assigns)]:
                for side, name in REF.findall(text):
                    owner = c if side == "a" else seen
                    known = early if side == "a" else {a.effect for x in seen.loops if loop.context and x.stage < loop.stage for a in x.assigns if not a.to_seen}
                    if name in owner.effects and name not in known:
                        out.append(f"EFFECT_READ_IN_LOOP: {owner.name}.{name}")
                    elif name != "id" and name not in owner.states and name not in owner.effects:
                        out.append(f"UNKNOWN_FIELD: {owner.name}.{name}")
    return out


def reads_effects(loop: Loop, side: str, c: AgentClass) -> bool:
    return any(s == side and f in c.effects for s, f in REF.findall(" ".join([loop.where, *(a.value for a in loop.assigns)])))


def invert(world: dict[str, AgentClass]) -> dict[str, AgentClass]:
    """The same world with every non-local assignment made local: the receiver
    loops over the writers, with the bound mirrored.

    Where the writer passes on what its own loop has gathered (a two-hop script),
    the receiver reads the writer's effect: whoever runs the loop for a part must
    rebuild it from the writer's neighbours, so the part needs agents of the sum of
    both bounds (``runtime.closed_ticks`` with ``two_hop_halo``)."""
    loops = {n: [] for n in world}
    for c in world.values():
        for loop in c.loops:
            away = [a for a in loop.assigns if a.to_seen]
            stay = tuple(a for a in loop.assigns if not a.to_seen)
            if stay:
                loops[c.name].append(replace(loop, assigns=stay))
            if away:
                mirrored = {axis: (-hi, -lo) for axis, (lo, hi) in loop.bound.items()}
                back = replace(loop, seen=c.name, bound=mirrored, where=swap(loop.where), assigns=tuple(Assign(a.effect, swap(a.value)) for a in away))
                loops[loop.seen].append(replace(back, context=reads_effects(back, "b", c)))
    return {n: replace(c, loops=tuple(loops[n])) for n, c in world.items()}


def two_hop_halo(world: dict[str, AgentClass]) -> dict[str, tuple[int, int]]:
    """How far, for an axis, a tick's local loops look in all: a loop's bound,
    plus the bounds of the loops whose effects it reads of the agents seen."""
    out: dict[str, int] = {}
    for c in world.values():
        for loop in c.loops:
            inner = [x for x in world[loop.seen].loops if loop.context and x.stage < loop.stage]
            for axis, b in loop.bound.items():
                far = max(map(abs, b)) + max((max(map(abs, x.bound.get(axis, (0, 0)))) for x in inner), default=0)
                out[axis] = max(out.get(axis, 0), far)
    return {axis: (-far, far) for axis, far in out.items()}


def fuse_loops(c: AgentClass) -> AgentClass:
    """Loops over one extent with one bound become one pair relation."""
    out: list[Loop] = []
    kind = lambda x: replace(x, assigns=())
    for loop in c.loops:
        for i, o in enumerate(out):
            if kind(o) == kind(loop) and not {a.effect for a in o.assigns} & {a.effect for a in loop.assigns}:
                out[i] = replace(o, assigns=o.assigns + loop.assigns)
                break
        else:
            out.append(loop)
    return replace(c, loops=tuple(out))


def drop_dead_effects(world: dict[str, AgentClass]) -> dict[str, AgentClass]:
    """Effects that no update rule, death rule or later stage reads."""
    out = {}
    live = {}
    for c in world.values():
        loops = [x for o in world.values() for x in o.loops]
        text = " ".join([*(s.update or "" for s in c.states.values()), *(e for _, e in c.lets), c.die or "", *((c.born.when, *c.born.states.values()) if c.born else ()), *(t for x in loops for t in (x.where, *(a.value for a in x.assigns)))])
        live[c.name] = {e for e in c.effects if re.search(rf"\b{e}\b", text)}
    for c in world.values():
        loops = []
        for x in c.loops:
            keep = tuple(a for a in x.assigns if a.effect in live[x.seen if a.to_seen else c.name])
            if keep:
                loops.append(replace(x, assigns=keep))
        out[c.name] = replace(c, loops=tuple(loops), effects={e: v for e, v in c.effects.items() if e in live[c.name]})
    return out


def prepare(world: dict[str, AgentClass]) -> dict[str, AgentClass]:
    """Checked, without dead effects, loops fused: what ticks and runs execute."""
    if bad := check(world):
        raise ValueError("; ".join(bad))
    return {n: fuse_loops(c) for n, c in drop_dead_effects(world).items()}
