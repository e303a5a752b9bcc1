"""Plain descriptions: models, table profiles, batch plans, results of a run."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


class BudgetTooSmall(ValueError):
    """Even one row of each side doesn't fit a call with its answer."""


class FeeLimit(RuntimeError):
    """The forecast or the ledger exceeds the fee that was allowed."""


class OverflowSignal(RuntimeError):
    """A block join whose answers were cut off, when that is to be an error."""

    def __init__(self, cells: int, run: JoinRun):
        super().__init__(f"{cells} answers were cut off")
        self.cells, self.run = cells, run


@dataclass(frozen=True)
class ModelProfile:
    """Limits and prices; prices are cents per 1,000 tokens."""

    context_tokens: int = 2000
    reliable_tokens: int | None = None
    read_price: float = 3.0
    write_price: float = 6.0
    max_output: int | None = None
    stop_word: bool = True
    timeout_s: float = 20.0
    temperature: float = 0.0
    max_retries: int = 3
    max_parallel: int | None = None  # calls at a time; None: as many as there are cores

    @property
    def write_ratio(self) -> float:
        return self.write_price / self.read_price

    @property
    def limit(self) -> int:
        return min(self.context_tokens, self.reliable_tokens or self.context_tokens)


@dataclass(frozen=True)
class TableProfile:
    rows: int
    width_mean: float
    width_max: int
    width_p95: int = 0


@dataclass(frozen=True)
class BatchPlan:
    batch_left: int
    batch_right: int
    estimate: float
    budget: float
    expected_calls: int
    expected_cost: float
    continuous_left: float
    continuous_right: float


@dataclass(frozen=True)
class Round:
    number: int
    estimate: float
    batch_left: int
    batch_right: int
    calls: int
    overflow: bool


@dataclass
class JoinRun:
    """pairs: (left_id, right_id); ledger: one row per call, voided ones included."""

    run_id: str
    method: str
    pairs: DataFrame
    ledger: DataFrame
    plan: BatchPlan | None = None
    rounds: list[Round] = field(default_factory=list)
    seconds: float = 0.0

    def usage(self) -> DataFrame:
        return self.ledger.agg(F.count("*").alias("calls"), F.coalesce(F.sum("tokens_read"), F.lit(0)).cast("long").alias("tokens_read"), F.coalesce(F.sum("tokens_written"), F.lit(0)).cast("long").alias("tokens_written"), F.coalesce(F.sum("latency_ms"), F.lit(0.0)).alias("latency_ms"))

    def fees(self, model: ModelProfile) -> DataFrame:
        """Cents, exact."""
        cents = lambda tokens, price: F.col(tokens).cast("decimal(18,0)") * F.lit(price / 1000).cast("decimal(12,6)")
        return self.usage().select((cents("tokens_read", model.read_price) + cents("tokens_written", model.write_price)).cast("decimal(24,6)").alias("fee"))

    def quality(self, truth: DataFrame) -> DataFrame:
        from semjoin.operators.quality import quality

        return quality(self.pairs, truth)

    def with_payload(self, left: DataFrame, right: DataFrame, left_id: str = "row_id", right_id: str = "row_id") -> DataFrame:
        l = left.select(*[F.col(c).alias("left_id" if c == left_id else f"left_{c}") for c in left.columns])  # noqa: E741
        r = right.select(*[F.col(c).alias("right_id" if c == right_id else f"right_{c}") for c in right.columns])
        return self.pairs.join(l, "left_id").join(r, "right_id")
