"""Colourings as expressions of the vertex id and the trial: never stored, never random at run time, so a
retried task sees the colours of its first attempt.

``affine`` is fixed by two constants that DuckDB evaluates alike; ``poly`` is a polynomial of degree k - 1
modulo a prime, k-wise independent, which is all that an unbiased estimate needs; ``xxhash`` is the
fastest.
"""

from __future__ import annotations

from dataclasses import dataclass
from random import Random

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

PRIME = 2147483647
# Fixed constants of the affine colouring.
MULTIPLIER, INCREMENT = 1103515245, 12345


@dataclass(frozen=True)
class Coloring:
    """color(v, trial) in 0..k-1."""

    k: int
    kind: str = "xxhash"
    seed: int = 1
    trials: int = 1

    def color(self, v: Column, trial: Column) -> Column:
        if self.kind == "affine":
            return self._affine(v, trial)
        if self.kind == "poly":
            return self._poly(v, trial)
        if self.kind == "xxhash":
            return F.pmod(F.xxhash64(v, trial, F.lit(self.seed)), F.lit(self.k))
        raise ValueError(f"no colouring {self.kind!r}")

    def _affine(self, v: Column, trial: Column) -> Column:
        factor = F.lit(MULTIPLIER).cast("long") + 2 * trial
        return ((factor * (v % PRIME) + INCREMENT) % PRIME) % self.k

    def _poly(self, v: Column, trial: Column) -> Column:
        x = (v % PRIME).cast("long")
        value = F.lit(0).cast("long")
        for c in range(self.k):
            drawn = [Random(f"{self.seed}/{t}/{c}").randrange(PRIME) for t in range(self.trials)]
            value = (value * x + F.element_at(F.array(*[F.lit(d).cast("long") for d in drawn]), trial.cast("int") + 1)) % PRIME
        return value % self.k


def affine_sql(v: str, k: int, trial: str = "0") -> str:
    """The affine colouring as SQL text."""
    return f"((({MULTIPLIER} + 2 * {trial}) * ({v} % {PRIME}) + {INCREMENT}) % {PRIME}) % {k}"


@dataclass(frozen=True)
class TableColoring:
    """An explicit colouring: rows (trial, v, color). ``mapped`` holds at most max_rows rows as a map literal,
    which is meant for exhaustive tests on tiny graphs."""

    k: int
    mapped: dict[tuple[int, int], int]
    trials: int = 1
    kind: str = "table"

    @classmethod
    def from_df(cls, df: DataFrame, k: int, max_rows: int = 5000) -> TableColoring:
        rows = df.select("trial", "v", "color").limit(max_rows + 1).collect()
        if len(rows) > max_rows:
            raise ValueError(f"an explicit colouring has {max_rows} rows at most; use an expression for more")
        return cls(k, {(r[0], r[1]): r[2] for r in rows}, len({r[0] for r in rows}))

    def color(self, v: Column, trial: Column) -> Column:
        cells = [x for (t, n), c in self.mapped.items() for x in (F.lit(f"{t}/{n}"), F.lit(c))]
        return F.element_at(F.create_map(*cells), F.concat_ws("/", trial.cast("string"), v.cast("string"))).cast("long")
