"""Timing traces of one-at-a-time runs: checkpoints of the elapsed time, and where it went, by engine and control.

The engine marks and probes keys in a dictionary, the control compares each arrival with the leaders in turn. Both run
in one task on one core, so that their times are those of the method and not of a cluster; the answers are the same.
"""

from __future__ import annotations

import time
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from overlapkeys.plans.overlap_plan import OverlapPlan

STEP, FINE_STEP, FINE = 1000, 10, 2000  # a checkpoint each STEP items, each FINE_STEP among the first FINE
PHASES = ("read_s", "keys_s", "store_s", "output_s")
SCHEMA = "run string, n bigint, clusters bigint, elapsed_s double, read_s double, keys_s double, store_s double, output_s double"


def whole(frames: Iterator[pd.DataFrame]) -> pd.DataFrame:
    """The one task's items in order of arrival; no rows of any column for an empty table."""
    parts = list(frames)
    return pd.concat(parts).sort_values("ordinal") if parts else pd.DataFrame({"ordinal": [], "size": [], "sig": [], "s": []})


class Engine:
    def __init__(self, plan: OverlapPlan):
        self.probe = {x: plan.combos(x, "probe") for x in plan.sizes}
        self.mark = {x: plan.combos(x, "mark") for x in plan.sizes}
        self.store: dict[tuple, int] = {}

    def keys(self, sig: list) -> list[tuple]:
        return [(t, *[sig[p - 1] for p in pos]) for t, pos in self.probe[len(sig)]]

    def assign(self, ordinal: int, sig: list, keys: list[tuple]) -> int:
        hits = [h for k in keys if (h := self.store.get(k)) is not None]
        if hits:
            return min(hits)
        self.lead(ordinal, sig)
        return ordinal

    def lead(self, ordinal: int, sig: list) -> None:
        for t, pos in self.mark[len(sig)]:
            self.store.setdefault((t, *[sig[p - 1] for p in pos]), ordinal)


class Control:
    def __init__(self, plan: OverlapPlan):
        self.rule, self.leaders = plan.rule, []

    def keys(self, sig: list) -> frozenset:
        return frozenset(sig)

    def assign(self, ordinal: int, sig: list, own: frozenset) -> int:
        holds, x = self.rule.holds, len(own)
        for leader, other in self.leaders:
            if holds(len(own & other), x, len(other)):
                return leader
        self.leaders.append((ordinal, own))
        return ordinal


RUNS = {"engine": Engine, "control": Control}


def timed_run(sigs: DataFrame, plan: OverlapPlan, run: str, first: int | None = None) -> DataFrame:
    """(run, n, clusters, elapsed_s and its parts): checkpoints of a run over the first items, all if ``first`` is None."""
    make = RUNS[run]

    def go(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        pdf = whole(frames)
        clock, method = time.perf_counter, make(plan)
        spent, out, points, clusters = [0.0] * 4, [], [], 0
        rows = zip(pdf["ordinal"].tolist(), pdf["sig"].tolist())
        last = clock()
        for n in range(1, len(pdf) + 1):
            ordinal, sig = next(rows)
            sig = list(sig)
            a = clock()
            keys = method.keys(sig)
            b = clock()
            home = method.assign(ordinal, sig, keys)
            c = clock()
            out.append((home, ordinal, "-".join(sig)))
            clusters += home == ordinal
            d = clock()
            for k, s in enumerate((a - last, b - a, c - b, d - c)):
                spent[k] += s
            if n % (FINE_STEP if n <= FINE else STEP) == 0 or n == len(pdf):
                points.append((run, n, clusters, sum(spent), *spent))
            last = clock()
        yield pd.DataFrame(points, columns=[c.split()[0] for c in SCHEMA.split(", ")])

    some = sigs if first is None else sigs.filter(F.col("ordinal") <= first)
    return some.select("ordinal", "sig").coalesce(1).mapInPandas(go, SCHEMA)


def phases(trace: DataFrame) -> DataFrame:
    """(run, phase, seconds): where the time of each run's last checkpoint went."""
    last = trace.groupBy("run").agg(*[F.max_by(p, "n").alias(p) for p in PHASES])
    return last.unpivot("run", list(PHASES), "phase", "seconds")


def growth(trace: DataFrame, least: int = 100) -> DataFrame:
    """(run, power): the power of n by which the elapsed time grows, by least squares over the logarithms."""
    some = trace.filter((F.col("n") >= least) & (F.col("elapsed_s") > 0))
    return some.groupBy("run").agg(F.regr_slope(F.ln("elapsed_s"), F.ln("n")).alias("power"))
