"""Connected components of an edge table, by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from overlapkeys.session import drop, settle


HUBS = 10_000  # a node with over one in so many of the rows is a hub; there are fewer than so many of them
SMALL = 1_000  # rows that no node must have to be treated alike


def _toward_least(pairs: DataFrame, rows: int) -> DataFrame:
    """(u, v) with the least of u and its v's. ``rows``: how many pairs there are at most.

    Hubs are told from the others by their counts: the least of each hub is broadcast, so its rows stay where
    they are; only rows of other nodes are shuffled to meet theirs.
    """
    least = pairs.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n"))
    told = least.select("u", F.least("u", "m").alias("m"), "n")
    if rows <= SMALL:
        return pairs.join(told.drop("n"), "u")
    hubs = told.filter(F.col("n") > max(SMALL, rows // HUBS)).drop("n").collect()  # fewer than HUBS rows
    if not hubs:
        return pairs.join(told.drop("n"), "u")
    table = F.broadcast(pairs.sparkSession.createDataFrame(hubs, "u bigint, m bigint"))
    others = pairs.join(table.select("u"), "u", "left_anti")
    return pairs.join(table, "u").union(others.join(told.drop("n"), "u"))


def component_labels(edges: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 60) -> DataFrame:
    """(node, label) for every node of ``edges``; label is the least node that it reaches.

    A round hangs greater neighbours on the least neighbour, then smaller ones; the number of rounds
    grows with the logarithm of the longest shortest path. Each round is written to the shared
    folder, and only a count and a checksum come to the driver. Loops and nulls are dropped.
    """
    now = edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).filter("u <> v").distinct()
    now, seen = settle(now, "edges"), None
    rows = now.count()
    for _ in range(max_rounds):
        both = now.union(now.select("v", "u"))
        large = _toward_least(both, 2 * rows).filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        if rows > SMALL:  # its hubs are counted first
            large = settle(large, "edges")
        small = _toward_least(large.filter("u > v"), 2 * rows)
        down = small.select(F.col("v").alias("u"), F.col("m").alias("v"))
        last, now = now, settle(down.union(small.select("u", F.col("m").alias("v"))).filter("u <> v").distinct(), "edges")
        drop(last, large)
        sums = F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))
        state = tuple(now.agg(F.count("*"), sums).first())
        if state == seen:
            break
        seen, rows = state, state[0]
    else:
        raise RuntimeError(f"components not settled after {max_rounds} rounds")
    stars = now.groupBy("u").agg(F.min("v").alias("label")).select(F.col("u").alias("node"), "label")
    roots = stars.select(F.col("label").alias("node"), "label").distinct()
    return stars.union(roots)
