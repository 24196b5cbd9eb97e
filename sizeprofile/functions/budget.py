"""Privacy budget: levels compose one after the other, nodes of a level side by side, post-processing is free."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession


class BudgetExceeded(ValueError):
    pass


@dataclass
class BudgetLedger:
    total: float
    entries: list[tuple[str, str, float]] = field(default_factory=list)

    @property
    def spent(self) -> float:
        """Sum over steps; scopes of one step touch disjoint entities, so a step costs its largest entry."""
        steps: dict[str, float] = {}
        for step, _, eps in self.entries:
            steps[step] = max(steps.get(step, 0.0), eps)
        return sum(steps.values())

    def spend(self, step: str, eps: float, scope: str = "all nodes") -> float:
        if eps <= 0:
            raise ValueError("epsilon must be positive")
        self.entries.append((step, scope, eps))
        if self.spent > self.total * (1 + 1e-12):
            self.entries.pop()
            raise BudgetExceeded(f"{step}: {eps} does not fit into {self.total}")
        return eps

    def split(self, levels: int, weights: list[float] | None = None) -> list[float]:
        """The budget of each level, entered in the ledger."""
        weights = weights or [1.0] * levels
        if len(weights) != levels or min(weights) <= 0:
            raise ValueError("one positive weight a level")
        left = self.total - self.spent
        return [self.spend(f"level {k}", left * w / sum(weights)) for k, w in enumerate(weights)]

    def to_df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.entries, "step string, scope string, eps double")
