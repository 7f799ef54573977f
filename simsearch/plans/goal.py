"""What a query asks for: how many results, and how much difference between them counts."""

from __future__ import annotations

from dataclasses import dataclass
from decimal import ROUND_CEILING, ROUND_FLOOR, Decimal

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Goal:
    """Between kmin and kmax results; lam is the weight of the spread, 1 - lam that of closeness.

    Sizes are worked out in decimals, so that 1.1 x 30 is 33 and not a little more."""

    kmin: int = 25
    kmax: int = 55
    lam: float = 0.5

    def __post_init__(self):
        if not (1 <= self.kmin <= self.kmax and 0 <= self.lam <= 1):
            raise ValueError("need 1 <= kmin <= kmax and 0 <= lam <= 1")

    @property
    def _wide(self) -> Decimal:
        return 1 + Decimal(str(self.lam))

    @property
    def most(self) -> int:
        """Candidates that are kept at most."""
        return int((self._wide * self.kmax).to_integral_value(ROUND_FLOOR))

    @property
    def least(self) -> int:
        """Candidates that relaxation looks for."""
        return min(int((self._wide * self.kmin).to_integral_value(ROUND_CEILING)), self.most)

    def share(self, candidates: int) -> int:
        """Results out of so many candidates."""
        n = int((Decimal(candidates) / self._wide).to_integral_value(ROUND_FLOOR))
        return min(max(n, self.kmin), self.kmax, candidates)

    @property
    def quota(self) -> Decimal:
        """Strings of the first cluster after which a walk moves on."""
        return (1 - Decimal(str(self.lam))) * self.kmin

    def shares(self) -> list[int]:
        """share(n) for n from 0 to most, to look up in a plan."""
        return [self.share(n) for n in range(self.most + 1)]

    def share_of(self, candidates: Column) -> Column:
        return F.element_at(F.array(*[F.lit(x) for x in self.shares()]), (candidates + 1).cast("int"))


class GoalGrid:
    """Several goals for the same queries in one plan. Query q under goal i is a query of its own, q * PLACES + i; the
    sizes are columns that depend on it, so that operators which take a Goal take a grid as well."""

    PLACES = 1000

    def __init__(self, goals: list[Goal]):
        if not 0 < len(goals) <= self.PLACES:
            raise ValueError(f"a grid has 1 to {self.PLACES} goals")
        self.goals = goals
        self.place = F.pmod(F.col("qid"), F.lit(self.PLACES))
        self.kmin, self.kmax, self.lam, self.least, self.most = (self.pick([getattr(g, c) for g in goals]) for c in ("kmin", "kmax", "lam", "least", "most"))

    def pick(self, values: list) -> Column:
        """The value of the row's goal."""
        return F.element_at(F.array(*[F.lit(v) for v in values]), (self.place + 1).cast("int"))

    def share_of(self, candidates: Column) -> Column:
        shares = F.array(*[F.array(*[F.lit(x) for x in g.shares()]) for g in self.goals])
        return F.element_at(F.element_at(shares, (self.place + 1).cast("int")), (candidates + 1).cast("int"))

    def over(self, rows: DataFrame) -> DataFrame:
        """rows (with qid) once per goal."""
        each = rows.withColumn("__place", F.explode(F.sequence(F.lit(0), F.lit(len(self.goals) - 1))))
        return each.withColumn("qid", F.col("qid").cast("long") * self.PLACES + F.col("__place")).drop("__place")
