"""Specifications of guarantees and samples, and results with their ledgers."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession


@dataclass(frozen=True)
class GuaranteeSpec:
    """Targets against the reference algorithm's output, and the failure probability."""

    recall: float | None = None
    precision: float | None = None
    accuracy: float | None = None
    delta: float = 0.2

    def __post_init__(self) -> None:
        for name in ("recall", "precision", "accuracy"):
            x = getattr(self, name)
            if x is not None and not 0 < x <= 1:
                raise ValueError(f"{name} must be in (0, 1]")
        if not 0 < self.delta < 1:
            raise ValueError("delta must be in (0, 1)")


@dataclass(frozen=True)
class SampleSpec:
    """How many rows the oracle labels for planning, and how they are drawn."""

    fraction: float = 1e-4
    min_rows: int = 100
    max_rows: int = 100_000
    uniform_mix: float = 0.5
    weight_power: float = 0.5
    seed: int = 0

    def size(self, n: int) -> int:
        return min(self.max_rows, max(self.min_rows, round(n * self.fraction)))


@dataclass
class NLResult:
    """Rows, calls by route (counted from data) and notes on the plan that ran."""

    df: DataFrame
    calls: dict[str, int] = field(default_factory=dict)
    plan: dict = field(default_factory=dict)

    def ledger(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(sorted(self.calls.items()), "route string, calls long")

    @property
    def oracle_calls(self) -> int:
        """Calls made: what the routes need, without answers of the sample that are used again."""
        return sum(n for route, n in self.calls.items() if route.startswith("oracle")) - self.plan.get("reused", 0)
