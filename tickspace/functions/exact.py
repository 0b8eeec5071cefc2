"""Exact integer arithmetic as SQL text that Spark and other engines agree on.

Positions and velocities are BIGINT lattice units, so sums are associative and a
tick's result does not depend on partitioning.  Every function takes and gives
SQL expressions.
"""

from __future__ import annotations

NOISE_MOD = 2147483647


def floordiv(a: str, b: str | int) -> str:
    """Floor division, also of negative numbers (magnitudes below 2**53)."""
    return f"CAST(floor(CAST(({a}) AS DOUBLE) / ({b})) AS BIGINT)"


def noise(id_: str, tick: int | str, stream: int = 0, seed: int = 7) -> str:
    """A draw in [0, 2**31 - 1) that depends on nothing but its arguments."""
    one = f"((({id_}) % {NOISE_MOD} + {NOISE_MOD} + {seed * 7919 + 1}) % {NOISE_MOD} * 48271) % {NOISE_MOD}"
    two = f"((({one}) + ({tick}) * 69621 + {stream * 40692 + 13}) % {NOISE_MOD} * 39373) % {NOISE_MOD}"
    return f"(((({two}) + 12345) % {NOISE_MOD} * 16807) % {NOISE_MOD})"


def unit(x: str, y: str, component: str, scale: int = 1000) -> str:
    """One component of (x, y) scaled to length ``scale``; 0 for no length."""
    length = f"sqrt(CAST(({x}) * ({x}) + ({y}) * ({y}) AS DOUBLE))"
    return f"CASE WHEN ({x}) = 0 AND ({y}) = 0 THEN CAST(0 AS BIGINT) ELSE CAST(floor(CAST(({component}) * {scale} AS DOUBLE) / {length}) AS BIGINT) END"


def clamp(value: str, low: str | int, high: str | int) -> str:
    return f"greatest(CAST({low} AS BIGINT), least(CAST({high} AS BIGINT), {value}))"


def pack(key: str, payload: str) -> str:
    """Key and payload in one number, so that a minimum is an arg-min; both
    are non-negative and below 2**31.  A payload beyond that overflows, which
    stops the query in either engine; minima of ``struct(key, id)`` have no limit."""
    return f"(({key}) * 2147483648 + ({payload}) + 9223372036854775807 * CASE WHEN ({payload}) < 0 OR ({payload}) > 2147483647 THEN 2 ELSE 0 END)"


def packed_key(value: str) -> str:
    return floordiv(value, 2147483648)


def packed_payload(value: str) -> str:
    return f"(({value}) % 2147483648)"


def to_fixed(value: str, scale: int) -> str:
    return f"CAST(floor(({value}) * {scale} + CAST(0.5 AS DOUBLE)) AS BIGINT)"


def from_fixed(value: str, scale: int) -> str:
    return f"(CAST(({value}) AS DOUBLE) / {scale})"
