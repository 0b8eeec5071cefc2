"""Sums over pairs inside a kernel: pairs are met in batches and never handed out.

A sum is *foldable* if a pair adds products of a part that depends on the offset
b - a alone and a part that reads the seen agent alone.  The first parts are read
off tables by offset, the second are columns.  What a kernel holds is a batch of
pairs, whatever their number; results are exact integers, the same as those of the
pairs.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, replace

import numpy as np
from pyspark.errors import ArithmeticException
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..plans.agents import REF, Assign, Effect, Loop, swap

#: most offsets that a table is made for
WIDEST = 1 << 21


@dataclass(frozen=True)
class Term:
    """What a pair adds to ``name``: the table's value at its offset (-1: one) times
    the seen agent's ``weight`` (SQL over b's columns; none: one)."""

    name: str
    table: int = -1
    weight: str = ""


@dataclass(frozen=True)
class Fold:
    terms: tuple[Term, ...]
    tables: tuple[tuple[tuple[int, ...], np.ndarray], ...] = ()  #: axes (places in the bound), values by offset
    where: int = -1  #: table of ones and zeros: which offsets count at all
    many: str = ""  #: column of b: how many agents a row stands for
    alone: bool = False  #: readers are among the seen rows themselves and do not see themselves

    @property
    def names(self) -> list[str]:
        return list(dict.fromkeys(t.name for t in self.terms))

    @property
    def weights(self) -> list[str]:
        return list(dict.fromkeys(t.weight for t in self.terms if t.weight))

    def readers(self, left: DataFrame) -> DataFrame:
        """With the weights that a reader has for itself."""
        own = lambda w: F.coalesce(F.expr(re.sub(r"\bb_", "a_", w)), F.lit(0)).cast("bigint")
        return left.select("*", *[own(w).alias(f"_w{k}") for k, w in enumerate(self.weights)]) if self.alone else left

    def seen(self, right: DataFrame, keep: list[str]) -> DataFrame:
        """``keep`` and the weights of all agents that a row stands for."""
        many = F.col(self.many) if self.many else F.lit(1)
        weights = [F.coalesce(F.expr(w) * many, F.lit(0)).cast("bigint").alias(f"_w{k}") for k, w in enumerate(self.weights)]
        return right.select(*keep, *weights, *([many.cast("bigint").alias("_many")] if self.many else []))

    def run(self, find, ax: np.ndarray, bx: np.ndarray, low: np.ndarray, high: np.ndarray, self_: np.ndarray, own: list[np.ndarray], weights: list[np.ndarray], many: np.ndarray | None) -> tuple[np.ndarray, np.ndarray]:
        """(agents seen, sums by name) of each reader; ``self_``: it is among
        the seen rows; ``own``, ``weights``: the weights of readers and of seen rows."""
        names, n = self.names, np.zeros(len(ax), np.int64)
        sums = np.zeros((len(names), len(ax)), np.int64)
        if not len(ax) or not len(bx):  # no row of itself either
            return n, sums
        at = {axes: _flat(axes, ax, bx, low, high) for axes, _ in self.tables}
        terms = [(names.index(t.name), t.table, self.weights.index(t.weight) if t.weight else -1) for t in self.terms]
        weight = lambda w: weights[w] if w >= 0 else many
        # where 64 bits may not do, sums are kept roughly too, to tell
        most = max([int(np.abs(v).max(initial=0)) for _, v in self.tables], default=1)
        risky = most * sum(float(np.abs(w.astype(float)).sum()) for w in [*weights, *([] if many is None else [many])]) >= 2.0**62
        rough = np.zeros(sums.shape) if risky else None

        def whole(readers, rows):
            n[readers] += len(rows) if many is None else many[rows].sum()
            for c, _, w in terms:
                sums[c, readers] += len(rows) if weight(w) is None else weight(w)[rows].sum()
                if risky and weight(w) is not None:
                    rough[c, readers] += weight(w)[rows].sum(dtype=float)

        for i, j in find(ax, bx, low, high, None if self.tables else whole):
            if not len(i):
                continue
            first = np.append(0, np.flatnonzero(i[1:] != i[:-1]) + 1)
            who, got = i[first], {}
            by = {axes: eb[j] - ea[i] for axes, (ea, eb) in at.items()}

            def value(k, w, kind=np.int64):
                if (k, w, kind) not in got:
                    t = self.tables[k][1][by[self.tables[k][0]]] if k >= 0 else None
                    v = None if weight(w) is None else weight(w)[j].astype(kind, copy=False)
                    if t is None and v is None:
                        got[k, w, kind] = np.diff(np.append(first, len(i)))
                    else:
                        got[k, w, kind] = np.add.reduceat(t if v is None else v if t is None else t * v, first, dtype=kind)
                return got[k, w, kind]

            n[who] += value(self.where, -1)
            for c, k, w in terms:
                sums[c, who] += value(k, w)
                if risky:
                    rough[c, who] += value(k, w, np.float64)
        if risky and np.abs(rough).max() >= 2.0**63:
            raise OverflowError("a sum over pairs does not fit 64 bits")
        if self.alone and ((low <= 0) & (high >= 0)).all():
            none = lambda k: 1 if k < 0 else int(self.tables[k][1][_index(self.tables[k][0], -low, low, high)])
            n -= none(self.where) * self_
            for c, k, w in terms:
                sums[c] -= none(k) * self_ * (own[w] if w >= 0 else 1)
        return n, sums


def _index(axes: tuple[int, ...], offset, low, high) -> int:
    """Where a table has the offset, counted from ``low``."""
    out = 0
    for x in axes:
        out = out * int(high[x] - low[x] + 1) + int(offset[x])
    return out


def _flat(axes: tuple[int, ...], ax: np.ndarray, bx: np.ndarray, low: np.ndarray, high: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Numbers of readers and seen rows whose difference is a pair's place in a table."""
    ea, eb = np.zeros(len(ax), np.int64), np.zeros(len(bx), np.int64)
    for x in axes:
        width, first = int(high[x] - low[x] + 1), min(ax[:, x].min(), bx[:, x].min())
        ea, eb = ea * width + (ax[:, x] - first + low[x]), eb * width + (bx[:, x] - first)
    return ea.astype(np.int32), eb.astype(np.int32)  # differences are below WIDEST, so cut bits do not matter


def sums(*columns: str) -> Fold:
    """Plain sums of the seen rows' columns."""
    return Fold(tuple(Term(f"b_{c}", weight=f"b_{c}") for c in columns))


def _whole(text: str) -> bool:
    """Do brackets and CASE ... END close, none before it opens?"""
    depth = 0
    for word in re.findall(r"[()]|\bCASE\b|\bEND\b", text):
        depth += 1 if word in ("(", "CASE") else -1
        if depth < 0:
            return False
    return depth == 0


def _offsets(text: str, bound) -> str:
    """With b.x - a.x as d_x; whole operands only, so that no precedence changes."""
    for axis in bound:
        for one, two, d in (("b", "a", f"d_{axis}"), ("a", "b", f"(0 - d_{axis})")):
            text = re.sub(rf"(?<=[(,])(\s*){one}\.{axis} - {two}\.{axis}(?=\s*[),])", rf"\g<1>{d}", text)
    return text


def _products(text: str, bound) -> list[tuple[str, str]] | None:
    """``text`` as a sum of (by offset, by seen agent), or None."""
    text = text.strip()
    by = _offsets(text, bound)
    if not REF.search(by):
        return [(by, "")]
    if by == text and all(side == "b" for side, _ in REF.findall(text)):
        return [("", text)]
    when = re.fullmatch(r"CASE WHEN (.*?) THEN (.*) ELSE 0 END", text, re.S)
    if when and all(map(_whole, when.groups())) and not re.search(r"\b(WHEN|ELSE)\b", _bare(when[2])):
        cond, inner = _offsets(when[1], bound), _products(when[2], bound)
        return None if inner is None or REF.search(cond) else [(f"CASE WHEN {cond} THEN {t or 1} ELSE 0 END", s) for t, s in inner]
    for at in (m.start() for m in re.finditer(r"\) \+ \(", text)):
        one, two = text[: at + 1], text[at + 4 :]
        if one[0] == "(" and two[-1] == ")" and all(map(_whole, (one[1:-1], two[1:-1]))):
            both = [_products(x[1:-1], bound) for x in (one, two)]
            return None if None in both else both[0] + both[1]
    return None


def _bare(text: str) -> str:
    """``text`` without what is in brackets."""
    while (less := re.sub(r"\([^()]*\)", "", text)) != text:
        text = less
    return text


def plan(agents: DataFrame, loop: Loop, some: list[tuple[Assign, Effect]], away: bool, many: str) -> Fold | None:
    """The fold of a loop over its own class, for assignments that all go to the
    looping agents or, ``away``, to the seen ones (then these are the readers)."""
    turn = swap if away else str
    bound = {x: (-hi, -lo) for x, (lo, hi) in loop.bound.items()} if away else loop.bound
    axes, where = list(bound), _offsets(turn(loop.where), bound)
    if REF.search(where) or loop.include_self:
        return None
    texts, terms = ([] if where == "true" else [f"CASE WHEN {where} THEN 1 ELSE 0 END"]), []
    for x, e in some:
        if e.combinator not in ("sum", "count") or e.default != 0 or (e.combinator == "count" and x.value.strip() != "1"):
            return None
        if re.search(r"\b(rand|randn|uuid|shuffle|monotonically_increasing_id)\b", x.value, re.I) or (found := _products(turn(x.value), bound)) is None:
            return None
        given = [s for _, s in found if s]
        for by, s in found:
            by = by if where == "true" else f"CASE WHEN {where} THEN {by or 1} ELSE 0 END"
            by = "" if by == "1" else by
            if by and by not in texts:
                texts.append(by)
            # a sum that is null for a pair adds none of its parts
            s = f"CASE WHEN {' AND '.join(f'({g}) IS NOT NULL' for g in given)} THEN {s or 1} ELSE 0 END" if given else ""
            terms.append(Term(x.effect, texts.index(by) if by else -1, REF.sub(lambda m: f"{m[1]}_{m[2]}", s)))
    tables = []
    for by in texts:
        used = tuple(k for k, x in enumerate(axes) if re.search(rf"\bd_{x}\b", by))
        size = [bound[axes[k]][1] - bound[axes[k]][0] + 1 for k in used]
        if np.prod(size, dtype=float) > WIDEST:
            return None
        tables.append((used, size))
    side = agents.select(*[F.col(c).alias(f"b_{c}") for c in agents.columns])
    out = Fold(tuple(terms), (), -1 if where == "true" else 0, many, True)
    if not all(isinstance(side.select(F.expr(w).alias("w")).schema["w"].dataType, T.IntegralType) for w in out.weights):
        return None
    values: dict[int, np.ndarray] = {}
    for used, size in {t[0]: t[1] for t in tables}.items():
        rest, at = F.col("id"), {}
        for k, n in reversed(list(zip(used, size))):
            at[k] = (rest % n + bound[axes[k]][0]).alias(f"d_{axes[k]}")
            rest = F.floor(rest / F.lit(n)).cast("bigint")
        mine = [k for k, t in enumerate(tables) if t[0] == used]
        rows = agents.sparkSession.range(int(np.prod(size, dtype=np.int64))).select("id", *at.values()).select("id", *[F.expr(texts[k]).alias(f"t{k}") for k in mine])
        if not all(isinstance(rows.schema[f"t{k}"].dataType, T.IntegralType) for k in mine):
            return None
        try:
            got = rows.toArrow()  # a row an offset
        except ArithmeticException:  # at an offset that perhaps no pair has
            return None
        order = np.argsort(got["id"].to_numpy())
        for k in mine:
            if got[f"t{k}"].null_count:
                return None
            values[k] = got[f"t{k}"].to_numpy().astype(np.int64)[order]
    small = lambda v: v.astype(next(t for t in (np.int16, np.int32, np.int64) if np.iinfo(t).min <= v.min() and v.max() <= np.iinfo(t).max))
    return replace(out, tables=tuple((t[0], small(values[k])) for k, t in enumerate(tables)))
