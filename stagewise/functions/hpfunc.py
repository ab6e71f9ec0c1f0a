"""Settings as functions of the step, in Spark expressions, and their pieces in canonical form.

A piece is (length, fn, args): fn is one of constant, exponential, linear, cosine.  Families are
cut at their own boundaries into pieces, so that equal beginnings have equal texts.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Piece:
    """``length`` steps of a function whose clock began ``since`` steps before the piece."""

    length: int
    fn: str
    args: tuple[float, ...]
    since: int = 0

    def text(self) -> str:
        """Canonical: functions of one value are that constant; numbers in shortest form."""
        fn, args = self.fn, self.args
        if fn == "exponential" and args[1] == 1 or fn == "linear" and args[0] == args[1] or fn == "cosine" and args[0] == args[2]:
            fn, args = "constant", args[:1]
        clock = "" if fn == "constant" or not self.since else f"+{self.since}"
        return f"{fn}({','.join(format(a, '.12g') for a in args)}){clock}"

    def value(self, t: int) -> float:
        t = t + self.since
        a = self.args
        if self.fn == "constant":
            return a[0]
        if self.fn == "exponential":
            return a[0] * a[1] ** t
        if self.fn == "linear":
            return a[0] + (a[1] - a[0]) * t / a[2]
        return a[2] + (a[0] - a[2]) * (1 + math.cos(math.pi * t / a[1])) / 2


def constant(value: float, length: int) -> list[Piece]:
    return [Piece(length, "constant", (float(value),))]


def exponential(init: float, gamma: float, length: int) -> list[Piece]:
    return [Piece(length, "exponential", (float(init), float(gamma)))]


def linear(init: float, end: float, total: int, length: int | None = None) -> list[Piece]:
    return [Piece(total if length is None else length, "linear", (float(init), float(end), float(total)))]


def cosine(init: float, period: int, floor: float = 0.0, length: int | None = None) -> list[Piece]:
    return [Piece(period if length is None else length, "cosine", (float(init), float(period), float(floor)))]


def multi_value(values: list[float], milestones: list[int], length: int) -> list[Piece]:
    """Constants that switch at absolute milestones; milestones at or beyond the end vanish."""
    ends = [*milestones, length]
    out, at = [], 0
    for v, end in zip(values, ends):
        if min(end, length) > at:
            out += constant(v, min(end, length) - at)
            at = min(end, length)
    return out


def step_decay(init: float, gamma: float, milestones: list[int], length: int) -> list[Piece]:
    return multi_value([round(init * gamma**k, 12) for k in range(len(milestones) + 1)], milestones, length)


def warmup(duration: int, target: float, then: list[Piece]) -> list[Piece]:
    """A straight line from 0 to the target, then pieces that start their own clock."""
    return linear(0.0, target, duration) + then


def cosine_restarts(init: float, period: int, length: int, floor: float = 0.0, multiplier: int = 1) -> list[Piece]:
    out, at = [], 0
    while at < length:
        own = min(period, length - at)
        out.append(Piece(own, "cosine", (float(init), float(period), float(floor))))
        at, period = at + own, period * multiplier
    return out


def cyclic(low: float, high: float, up: int, length: int) -> list[Piece]:
    out, at, rising = [], 0, True
    while at < length:
        own = min(up, length - at)
        out.append(Piece(own, "linear", (low, high, float(up)) if rising else (high, low, float(up))))
        at, rising = at + own, not rising
    return out


def cut(pieces: list[Piece], boundaries: set[int]) -> list[tuple[int, int, Piece]]:
    """(start, end, piece) with every boundary a start; a piece that is cut keeps its clock."""
    out, at = [], 0
    for p in pieces:
        end, start = at + p.length, at
        for b in sorted({x for x in boundaries if at < x < end} | {end}):
            out.append((start, b, Piece(b - start, p.fn, p.args, p.since + start - at)))
            start = b
        at = end
    return out


def align(settings: dict[str, list[Piece]]) -> list[tuple[int, int, str]]:
    """(start, end, config text) of several settings at once; boundaries are those of any of them.

    Where one setting's function runs on across a boundary, its text names the clock, so that the
    same function at another age is another configuration.  Ages inside one function don't split
    a node by themselves: canonical() joins equal neighbours.
    """
    ends, length = set(), min(sum(p.length for p in own) for own in settings.values())
    for own in settings.values():
        at = 0
        for p in own:
            at += p.length
            ends.add(at)
    parts = {k: cut(own, {e for e in ends if e <= length}) for k, own in settings.items()}
    out = []
    for rows in zip(*[[x for x in parts[k] if x[1] <= length] for k in sorted(parts)]):
        out.append((rows[0][0], rows[0][1], ";".join(f"{k}={r[2].text()}" for k, r in zip(sorted(parts), rows))))
    return out


def value(fn: Column, args: Column, t: Column) -> Column:
    """The value of a piece ``t`` steps after its clock began; args is array<double>."""
    a = [F.try_element_at(args, F.lit(k)) for k in (1, 2, 3)]
    return (
        F.when(fn == "constant", a[0])
        .when(fn == "exponential", a[0] * F.pow(a[1], t))
        .when(fn == "linear", a[0] + (a[1] - a[0]) * t / a[2])
        .when(fn == "cosine", a[2] + (a[0] - a[2]) * (1 + F.cos(F.pi() * t / a[1])) / 2)
    )


def text_udf():
    """(fn, args) -> canonical text as a vectorised function, for clients whose settings are columns; null where an argument is missing."""
    @F.pandas_udf("string")
    def hp_text(fn: pd.Series, args: pd.Series) -> pd.Series:
        return pd.Series([None if any(v is None or math.isnan(v) for v in a) else Piece(1, f, tuple(a)).text() for f, a in zip(fn, args)], dtype="object")

    return hp_text


def value_udf():
    """(canonical text, step) -> value as a vectorised function, for clients whose settings are texts in a column."""
    @F.pandas_udf("double")
    def hp_value(text: pd.Series, step: pd.Series) -> pd.Series:
        from stagewise.operators.training import parse_value

        return pd.Series([parse_value(x, int(t)) for x, t in zip(text, step)], dtype="float64")

    return hp_value
