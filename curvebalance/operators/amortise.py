"""When to rebalance: growth of the cost of a step since the last rebalance is added up and spent against what that rebalance cost."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, functions as F

POLICIES = ("amortised", "never", "always", "periodic")


@dataclass
class Controller:
    """query mode: cost of a step = time per operation times the largest number of buckets; compute mode: the measured time itself."""

    balance_cost: float
    buckets: int = 1
    mode: str = "query"
    policy: str = "amortised"
    period: int = 10
    base: float | None = None
    debt: float = 0.0
    trace: list[dict] = field(default_factory=list)

    def observe(self, time_max: float, n_ops: int = 1, buckets: int | None = None) -> bool:
        """Takes in a step; whether to rebalance now. The first step after a rebalance sets the base; only growth beyond it is charged."""
        if self.policy not in POLICIES or self.mode not in ("query", "compute"):
            raise ValueError("unknown policy or mode")
        if buckets is not None:
            self.buckets = buckets
        cost = time_max if self.mode == "compute" else (time_max / n_ops if n_ops else 0.0) * self.buckets
        if self.base is None:
            self.base = cost
        else:
            self.debt += max(0.0, cost - self.base)
        step = len(self.trace)
        now = {"amortised": self.debt >= self.balance_cost and self.debt > 0, "never": False, "always": True, "periodic": (step + 1) % self.period == 0}[self.policy]
        self.trace.append({"iter": step, "cost": cost, "base": self.base, "debt": self.debt, "rebalanced": now})
        return now

    def rebalanced(self, balance_cost: float, buckets: int | None = None) -> None:
        self.balance_cost, self.base, self.debt = balance_cost, None, 0.0
        if buckets is not None:
            self.buckets = buckets

    @property
    def amortised_cost(self) -> float:
        """Mean cost of a step, rebalances included."""
        return sum(t["cost"] for t in self.trace) / max(1, len(self.trace)) + sum(t["rebalanced"] for t in self.trace) * self.balance_cost / max(1, len(self.trace))


def step_cost(parts: DataFrame) -> DataFrame:
    """n_ops, time_max, buckets_max, cost of each step from a row a part (step, n_ops, time, buckets)."""
    g = parts.groupBy("step").agg(F.sum("n_ops").alias("n_ops"), F.max("time").alias("time_max"), F.max("buckets").alias("buckets_max"))
    return g.withColumn("cost", F.when(F.col("n_ops") > 0, F.col("time_max") / F.col("n_ops") * F.col("buckets_max")).otherwise(0.0))


def replay(spark, costs: DataFrame, balance_cost: float) -> DataFrame:
    """The controller over a table of steps (iter, cost) as a recursive query: iter, cost, debt, rebalanced. It is one row a step."""
    costs.createOrReplaceTempView("_step_costs")
    return spark.sql(f"""
        WITH RECURSIVE run(iter, cost, base, debt, rebalanced) AS (
          SELECT iter, cost, cost, CAST(0 AS DOUBLE), false FROM _step_costs WHERE iter = 0
          UNION ALL
          SELECT s.iter, s.cost, CASE WHEN r.rebalanced THEN s.cost ELSE r.base END,
                 CASE WHEN r.rebalanced THEN CAST(0 AS DOUBLE) ELSE r.debt + greatest(CAST(0 AS DOUBLE), s.cost - r.base) END,
                 CASE WHEN r.rebalanced THEN false ELSE r.debt + greatest(CAST(0 AS DOUBLE), s.cost - r.base) >= {float(balance_cost)!r}D END
          FROM run r JOIN _step_costs s ON s.iter = r.iter + 1
        ) SELECT iter, cost, debt, rebalanced FROM run""")
