"""Copy budgets from frequency and length, as column expressions."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

N_SHARDS, FULL_LENGTH, TAU_SEG, TAU_DEL = 100 / 3, 512, 32, 100


def _share(n: float | Column) -> Column:
    return F.lit(1.0) - F.lit(1.0) / (n if isinstance(n, Column) else F.lit(float(n)))


def expected_kept(freq: Column, n: float | Column = N_SHARDS) -> Column:
    """Copies of ``freq`` that random sharding over ``n`` shards leaves when a shard keeps only singletons."""
    return freq.cast("double") * F.pow(_share(n), freq.cast("double") - 1)


def kept_fraction(freq: Column, n: float | Column = N_SHARDS) -> Column:
    return F.pow(_share(n), freq.cast("double") - 1)


def length_factor(length: Column, full: float | Column = FULL_LENGTH) -> Column:
    """1 for the shortest texts, 0 from ``full`` characters on."""
    return F.greatest(F.lit(0.0), F.lit(1.0) - length.cast("double") / (full if isinstance(full, Column) else F.lit(float(full))))


@dataclass(frozen=True)
class RetentionPolicy:
    """Parameters of the adaptive budget."""

    n: float = N_SHARDS
    full_length: float = FULL_LENGTH
    tau_seg: int = TAU_SEG
    tau_del: int = TAU_DEL
    length_aware: bool = True
    ties: str = "document"

    def __post_init__(self):
        if self.n <= 1 or self.full_length <= 0:
            raise ValueError("n must exceed 1 and full_length 0")

    def real_budget(self, freq: Column, length: Column) -> Column:
        """The budget before rounding, at least 1."""
        alpha = length_factor(length, self.full_length) if self.length_aware else F.lit(1.0)
        return F.greatest(F.lit(1.0), F.lit(1.0) + (expected_kept(freq, self.n) - 1) * alpha)

    def budget(self, freq: Column, length: Column) -> Column:
        """Copies kept at first: 1 to ``freq``. The bounds also mend the power's underflow for huge frequencies."""
        alpha = length_factor(length, self.full_length) if self.length_aware else F.lit(1.0)
        raw = F.ceil(F.lit(1.0) + (expected_kept(freq, self.n) - 1) * alpha).cast("long")
        return F.least(freq.cast("long"), F.greatest(F.lit(1).cast("long"), raw))

    def max_budget(self) -> int:
        """The largest budget of any group; it bounds how many ranks matter."""
        q = 1 - 1 / self.n
        top = max(1, round(-1 / math.log(q)))
        return max(math.ceil(c * q ** (c - 1)) for c in range(max(1, top - 2), top + 3))


@dataclass(frozen=True)
class KeepK:
    """At most k copies of each group."""

    k: int = 1
    tau_seg: int = TAU_SEG
    tau_del: int = 0
    ties: str = "strict"

    def real_budget(self, freq: Column, length: Column) -> Column:
        return F.least(F.lit(float(self.k)), freq.cast("double"))

    def budget(self, freq: Column, length: Column) -> Column:
        return F.least(F.lit(self.k).cast("long"), freq.cast("long"))

    def max_budget(self) -> int:
        return self.k


def KeepOne(**options) -> KeepK:  # noqa: N802
    """One copy of each group; exact and without the run rule unless told otherwise."""
    return KeepK(1, **options)


@dataclass(frozen=True)
class KeepAll:
    """No deletion: the budget is the frequency."""

    tau_seg: int = TAU_SEG
    tau_del: int = 0
    ties: str = "document"

    def real_budget(self, freq: Column, length: Column) -> Column:
        return freq.cast("double")

    def budget(self, freq: Column, length: Column) -> Column:
        return freq.cast("long")

    def max_budget(self) -> int:
        return 1


def sql_budget(policy: RetentionPolicy = RetentionPolicy(), name: str = "retention_budget") -> str:
    """A SQL function for plain SQL users; Catalyst inlines its body."""
    q = repr(1 - 1 / policy.n)
    return f"""CREATE OR REPLACE TEMPORARY FUNCTION {name}(freq BIGINT, len BIGINT) RETURNS BIGINT
    RETURN least(freq, greatest(1L, CAST(ceil(1.0D + (freq * pow({q}D, freq - 1) - 1.0D) * greatest(0.0D, 1.0D - len / {float(policy.full_length)}D)) AS BIGINT)))"""
