"""The vertex program: what a user writes. Functions take and return Columns, so they are compiled into the stage."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Reduce:
    """How the contributions of one destination become one value. Must be commutative and associative."""

    columns: Callable[[Column], list[Column]]
    merge: Callable[[Column], list[Column]]
    finish: Callable[[Callable[[str], Column]], Column]
    names: tuple[str, ...] = ("r0",)
    salts: int = 1  # parts in which a destination's contributions are reduced first
    python: bool = False  # whether it runs in Python workers, all contributions of a destination at a time

    @classmethod
    def _one(cls, fn, again=None) -> Reduce:
        return cls(lambda c: [fn(c)], lambda c: [(again or fn)(c)], lambda part: part("r0"))

    @classmethod
    def min(cls) -> Reduce:
        return cls._one(F.min)

    @classmethod
    def max(cls) -> Reduce:
        return cls._one(F.max)

    @classmethod
    def sum(cls) -> Reduce:
        return cls._one(F.sum)

    @classmethod
    def count(cls) -> Reduce:
        return cls._one(F.count, F.sum)

    @classmethod
    def any(cls) -> Reduce:
        return cls._one(F.bool_or)

    @classmethod
    def collect(cls) -> Reduce:
        """Sorted list of contributions."""
        return cls(lambda c: [F.collect_list(c)], lambda c: [F.flatten(F.collect_list(c))], lambda part: F.array_sort(part("r0")))

    @classmethod
    def vector_sum(cls, fields: list[str]) -> Reduce:
        """Sums field by field of a struct contribution; the result is a struct of the same fields."""
        names = tuple(f"r{i}" for i in range(len(fields)))
        return cls(lambda c: [F.sum(c[f]) for f in fields], lambda c: [F.sum(c)], lambda part: F.struct(*(part(n).alias(f) for n, f in zip(names, fields, strict=True))), names)

    @classmethod
    def custom(cls, merge: Callable[[Column, Column], Column], zero: Column, salts: int = 16) -> Reduce:
        """Any commutative, associative merge with its zero. Contributions are gathered and folded in salts parts of a destination
        first, then the parts' results, so no row holds all that a hub gets."""
        fold = lambda values: F.aggregate(values, zero, merge)
        return cls(lambda c: [fold(F.collect_list(c))], lambda c: [fold(F.collect_list(c))], lambda part: part("r0"), salts=salts)

    @classmethod
    def grouped(cls, function: Callable, returns: str) -> Reduce:
        """A Python function of all contributions of a destination (a pandas Series) to one value: a grouped aggregate, for what no
        Column can say. There is no partial result, so a hub's contributions meet in one task: custom() where they can be merged."""

        def whole(values: pd.Series) -> float:
            return function(values)

        told = F.pandas_udf(whole, returns)
        return cls(lambda c: [told(c)], lambda c: [told(c)], lambda part: part("r0"), python=True)


class VertexProgram:
    """Override the functions; a state column is read as s['name'].

    direction: 'out' (messages follow edges), 'in' (against them) or 'both'.
    activation: 'changed' (the next senders are those whose state changed) or 'all'.
    apply_to: 'recipients' (apply runs where a value arrived) or 'all' (red is null elsewhere).
    stop_when_unchanged: end when no state changed, also if all vertices would go on sending.
    settles: a superstep past the end leaves the state as it is, though apply runs everywhere: supersteps can share a job.
    needs_dst_state: process may read the destination; without it that join is never planned.
    message_bytes: of a message, for a product by itself; run_program measures messages.
    """

    direction = "out"
    activation = "changed"
    apply_to = "recipients"
    needs_dst_state = False
    stop_when_unchanged = True
    settles = False
    max_supersteps: int | None = None
    state: tuple[str, ...] = ("value",)
    message_bytes = 16

    def init(self, v: Callable[[str], Column]) -> dict[str, Column]:
        """State columns of a vertex (v reads the columns of the vertex table)."""
        raise NotImplementedError

    def active0(self, v: Callable[[str], Column]) -> Column:
        return F.lit(True)

    def send(self, s: Callable[[str], Column]) -> Column:
        """The message; null: none."""
        raise NotImplementedError

    def process(self, m: Column, e: Column, dst: Callable[[str], Column] | None) -> Column:
        return m

    def reduce(self) -> Reduce:
        return Reduce.sum()

    def apply(self, red: Column, s: Callable[[str], Column]) -> dict[str, Column]:
        raise NotImplementedError

    def changed(self, old: Callable[[str], Column], new: Callable[[str], Column]) -> Column:
        out = F.lit(False)
        for name in self.state:
            out = out | ~old(name).eqNullSafe(new(name))
        return out
