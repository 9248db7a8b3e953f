"""Objective kernels: what a query's term is worth when a member leaves a bucket or arrives in one.

With c members of a query in a bucket, the improvement of a move from i to j is the sum over the vertex's
queries of leave(c_i) - arrive(c_j). Terms are integers (fixed point with 40 binary places for the
smoothed objective), so sums do not depend on the order of rows, and another engine gets the same ones.
They come from a table made once in Python, beyond whose end terms are zero. Where such a table would be long
(look-ahead over many final buckets), a term is the product of one entry for each ten binary digits of c.
"""

from __future__ import annotations

import functools
import math
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

PLACES = 40


#: Longest table of terms; beyond it terms are products of entries by DIGITS binary digits of the count.
SHORT, DIGITS = 4001, 10


def _terms(base: float) -> list[int] | None:
    """round(base^c * 2^40) for c = 0, 1, ... until it is zero; None if that takes more than SHORT entries."""
    out, c = [], 0
    while True:
        value = int(math.floor(base**c * (1 << PLACES) + 0.5))
        if value == 0:
            return out
        if c == SHORT:
            return None
        out.append(value)
        c += 1


def _factors(base: float) -> list[list[float]]:
    """Tables i = 0, 1, ... of base^(d * 2^(10 i)) for d = 0 to 1023, so many that terms of larger counts are zero; powers too small to matter are 0."""
    out = []
    while not out or (len(out) < 6 and base ** (1 << DIGITS * len(out)) * (1 << PLACES) >= 0.5):
        powers = (base ** (d << DIGITS * len(out)) for d in range(1 << DIGITS))
        out.append([x if x * (1 << PLACES + 2) >= 1 else 0.0 for x in powers])
    return out


@dataclass(frozen=True)
class Kernel:
    """objective 'pfanout', 'fanout' or 'clique'; t: final buckets below a bucket (look-ahead), 1 for none."""

    objective: str = "pfanout"
    p: float = 0.5

    @property
    def scale(self) -> int:
        return 1 << PLACES if self.objective == "pfanout" else 1

    @property
    def idle(self) -> int:
        """arrive(0): the term of a bucket that the query does not use."""
        return {"pfanout": 1 << PLACES, "fanout": 1, "clique": 0}[self.objective]

    def base(self, t: int = 1) -> float:
        return 1 - self.p / t

    def arrive(self, c: Column, t: int = 1) -> Column:
        if self.objective == "fanout":
            return F.when(c == 0, F.lit(1)).otherwise(F.lit(0)).cast("long")
        if self.objective == "clique":
            return -c.cast("long")
        terms = _terms(self.base(t))
        if terms is None:
            factors, mask = _factors(self.base(t)), (1 << DIGITS) - 1
            at = lambda i: F.shiftright(c.cast("long"), DIGITS * i).bitwiseAND(F.lit(mask)).cast("int") + 1
            power = functools.reduce(lambda x, y: x * y, (F.element_at(F.lit(f).cast("array<double>"), at(i)) for i, f in enumerate(factors)))
            return F.when(c < (1 << DIGITS * len(factors)), F.floor(power * F.lit(float(1 << PLACES)) + F.lit(0.5))).otherwise(F.lit(0)).cast("long")
        table = F.lit(terms).cast("array<bigint>")
        return F.when(c < len(terms), F.element_at(table, (c + 1).cast("int"))).otherwise(F.lit(0).cast("long"))

    def leave(self, c: Column, t: int = 1) -> Column:
        if self.objective == "fanout":
            return F.when(c == 1, F.lit(1)).otherwise(F.lit(0)).cast("long")
        return self.arrive(c - 1, t)

    def arrive_sql(self, c: str, t: int = 1) -> str:
        if self.objective == "fanout":
            return f"CAST(({c}) = 0 AS BIGINT)"
        if self.objective == "clique":
            return f"(-CAST({c} AS BIGINT))"
        terms = _terms(self.base(t))
        if terms is None:
            factors, mask = _factors(self.base(t)), (1 << DIGITS) - 1
            power = " * ".join(f"CAST([{', '.join(f'{x:.17e}' for x in f)}] AS DOUBLE[])[((CAST({c} AS BIGINT) >> {DIGITS * i}) & {mask}) + 1]" for i, f in enumerate(factors))
            return f"CASE WHEN ({c}) < {1 << DIGITS * len(factors)} THEN CAST(floor({power} * {float(1 << PLACES)!r} + 0.5) AS BIGINT) ELSE 0 END"
        return f"CASE WHEN ({c}) < {len(terms)} THEN CAST([{', '.join(map(str, terms))}][CAST({c} AS INTEGER) + 1] AS BIGINT) ELSE 0 END"

    def leave_sql(self, c: str, t: int = 1) -> str:
        return f"CAST(({c}) = 1 AS BIGINT)" if self.objective == "fanout" else self.arrive_sql(f"{c} - 1", t)

    def by_target(self, c: Column, t_col: Column, ts: list[int], kind: str) -> Column:
        """leave or arrive with a look-ahead that differs by bucket: one table per value of t."""
        side = self.leave if kind == "leave" else self.arrive
        if self.objective != "pfanout" or len(ts) == 1:
            return side(c, ts[0])
        out = F.lit(None).cast("long")
        for t in ts:
            out = F.when(t_col == t, side(c, t)).otherwise(out)
        return out


def pfanout_term(cnt: Column, p: float) -> Column:
    """1 - (1-p)^cnt."""
    return F.lit(1.0) - F.pow(F.lit(1.0 - p), cnt.cast("double"))


def gain_bin(gain: Column) -> Column:
    """Signed exponential bin: sign times the number of binary digits of the absolute value; 0 for 0."""
    size = F.length(F.bin(F.abs(gain))).cast("int")
    return F.when(gain > 0, size).when(gain < 0, -size).otherwise(F.lit(0))
