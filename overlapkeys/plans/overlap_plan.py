"""Which sub-signatures to enumerate: computed once from rule and sizes, a few thousand rows at most."""

from __future__ import annotations

from dataclasses import dataclass
from itertools import combinations
from math import comb

from pyspark.sql import DataFrame, SparkSession

from .rules import SimilarityRule

PLAN_LIMIT = 2_000_000  # positions in the broadcast plan; beyond it use the prefix filter

KEY_PLAN = "size int, role string, plan array<struct<tag: int, pos: array<int>>>"


@dataclass(frozen=True)
class OverlapPlan:
    rule: SimilarityRule
    sizes: tuple[int, ...]

    @classmethod
    def build(cls, rule: SimilarityRule, sizes) -> OverlapPlan:
        plan = cls(rule, tuple(sorted(set(map(int, sizes)))))
        if not rule.is_monotone(plan.sizes):
            raise ValueError("keys are exact only for a rule that more overlap never ends")
        return plan

    def need(self, x: int, y: int) -> int | None:
        return self.rule.required_overlap(x, y)

    def partner_sizes(self, x: int) -> list[int]:
        return [y for y in self.sizes if self.need(x, y) is not None]

    def overlap_sizes(self, y: int) -> list[int]:
        """Sub-signature sizes that an item of size y writes: what some prober of it needs."""
        return sorted({m for x in self.sizes if (m := self.need(x, y)) is not None})

    @property
    def uniform(self) -> bool:
        return len(self.sizes) == 1

    @property
    def identity(self) -> bool:
        return all(self.partner_sizes(x) == [x] and self.need(x, x) == x for x in self.sizes)

    def mark_count(self, x: int) -> int:
        return sum(comb(x, j) for j in self.overlap_sizes(x))

    def probe_count(self, x: int) -> int:
        return sum(comb(x, self.need(x, y)) for y in self.partner_sizes(x))

    def check_bound(self) -> bool:
        return all(self.mark_count(x) <= 2**x - 1 for x in self.sizes)

    def needs_df(self, spark: SparkSession) -> DataFrame:
        rows = [(x, y, m) for x in self.sizes for y in self.sizes if (m := self.need(x, y)) is not None]
        return spark.createDataFrame(rows, "x int, y int, need int")

    def counts_df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(x, self.mark_count(x), self.probe_count(x), 2**x - 1) for x in self.sizes], "size int, mark_keys bigint, probe_keys bigint, bound bigint")

    def combos(self, x: int, role: str) -> list[tuple[int, tuple[int, ...]]]:
        """(tag, 1-based positions) of the keys that an item of size x writes or looks up."""
        if role == "mark":
            return [(x, c) for j in self.overlap_sizes(x) for c in combinations(range(1, x + 1), j)]
        if role == "probe":
            return [(y, c) for y in self.partner_sizes(x) for c in combinations(range(1, x + 1), self.need(x, y))]
        if role == "simple":
            return [(0, c) for j in self.overlap_sizes(x) for c in combinations(range(1, x + 1), j)]
        if role == "pair":  # tag: the unordered pair of sizes
            return [(min(x, y) * 1000 + max(x, y), c) for y in self.partner_sizes(x) for c in combinations(range(1, x + 1), self.need(x, y))]
        raise ValueError(role)

    def to_df(self, spark: SparkSession, *roles: str) -> DataFrame:
        rows = [(x, role, self.combos(x, role)) for x in self.sizes for role in roles or ("mark", "probe")]
        held = sum(len(p) for _, _, plan in rows for _, p in plan)
        if held > PLAN_LIMIT:
            raise ValueError(f"{held} positions in the plan: too many keys an item; lower the sizes or use prefix_pairs")
        return spark.createDataFrame(rows, KEY_PLAN)


def advise(spark: SparkSession, histogram: DataFrame, thetas: list[str], caps: list[int]) -> DataFrame:
    """Keys that each threshold and cap would make for a table of (size, n): what fits a memory."""
    rows = []
    for theta in thetas:
        for cap in caps:
            plan = OverlapPlan.build(SimilarityRule.jaccard(theta), range(1, cap + 1))
            rows += [(theta, cap, x, plan.mark_count(x), plan.probe_count(x)) for x in plan.sizes]
    grid = spark.createDataFrame(rows, "theta string, cap int, size int, mark_keys bigint, probe_keys bigint")
    from pyspark.sql import functions as F

    capped = histogram.crossJoin(F.broadcast(spark.createDataFrame([(c,) for c in caps], "cap int")))  # as many rows as caps
    capped = capped.select("cap", F.least("size", "cap").alias("size"), "n").groupBy("cap", "size").agg(F.sum("n").alias("n"))
    joined = capped.join(F.broadcast(grid), ["cap", "size"])
    return joined.groupBy("theta", "cap").agg(F.sum("n").alias("items"), F.sum(F.col("n") * F.col("mark_keys")).alias("mark_rows"), F.sum(F.col("n") * F.col("probe_keys")).alias("probe_rows"))
