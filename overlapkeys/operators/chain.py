"""Chain clustering: every item marks its keys with its label, so clusters grow through members.

What a key keeps is a variant: all writers (``all``), the first one's (``first``) or the latest one's
label (``last``). An item's label is the least that it reads; labels only fall, so relaxation
with label-of-label jumps ends at the sequential result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from overlapkeys.plans.overlap_plan import OverlapPlan
from overlapkeys.session import settle

from .components import component_labels
from .keys import role_keys


BLOCK = 4096  # ordinals whose writers of one key pass one window; across blocks go only their aggregates


def _before(rows: DataFrame, value: Column, agg, pick, to: str) -> DataFrame:
    """Each (key, ordinal) row with the least or greatest ``value`` of the rows of its key that come earlier.

    A hot key's rows are spread over blocks of ordinals; a block carries one value to the later ones.
    """
    dealt = rows.withColumn("__v", value).withColumn("__b", F.floor(F.col("ordinal") / BLOCK))
    inside = W.partitionBy("key", "__b").orderBy("ordinal").rowsBetween(W.unboundedPreceding, -1)
    blocks = dealt.groupBy("key", "__b").agg(agg("__v").alias("__v"))
    carry = blocks.select("key", "__b", agg("__v").over(W.partitionBy("key").orderBy("__b").rowsBetween(W.unboundedPreceding, -1)).alias("__c"))
    met = dealt.withColumn("__i", agg("__v").over(inside)).join(carry.filter("__c is not null"), ["key", "__b"], "left")
    return met.withColumn(to, pick("__i", "__c")).drop("__v", "__b", "__i", "__c")


def key_roles(sigs: DataFrame, plan: OverlapPlan) -> DataFrame:
    """(key, ordinal, m, p): who writes and who reads each key."""
    marks = role_keys(sigs, plan, "mark").select("key", "ordinal", F.lit(True).alias("m"), F.lit(False).alias("p"))
    probes = role_keys(sigs, plan, "probe").select("key", "ordinal", F.lit(False).alias("m"), F.lit(True).alias("p"))
    return marks.union(probes).groupBy("key", "ordinal").agg(F.max("m").alias("m"), F.max("p").alias("p"))


def parent_edges(sigs: DataFrame, plan: OverlapPlan, marker: str) -> DataFrame:
    """(ordinal, parent): the writer whose label each read key holds when the item arrives; at most one a key."""
    agg, pick = (F.min, F.least) if marker == "first" else (F.max, F.greatest)
    read = _before(key_roles(sigs, plan), F.when(F.col("m"), F.col("ordinal")), agg, pick, "parent")
    return read.filter("p and parent is not null").select("ordinal", "parent").distinct()


def _jump(labels: DataFrame, pick) -> DataFrame:
    up = labels.select(F.col("ordinal").alias("label"), F.col("label").alias("higher"))
    return labels.join(up, "label").select("ordinal", pick("label", "higher").alias("label"))


def _settle_labels(labels: DataFrame, step, pick=F.least, max_rounds: int = 1000) -> DataFrame:
    labels, seen = settle(labels, "labels"), None
    for _ in range(max_rounds):
        state = labels.agg(F.sum("label")).first()[0]
        if state == seen:
            return labels
        labels, seen = settle(_jump(step(labels), pick), "labels"), state
    raise RuntimeError("labels did not settle")


def chain(sigs: DataFrame, plan: OverlapPlan, marker: str = "all", choice: str = "earliest") -> DataFrame:
    """(cluster_id, ordinal, elements); the id is the founder's ordinal. choice: earliest or latest label read."""
    least = choice == "earliest"
    agg, pick = (F.min, F.least) if least else (F.max, F.greatest)
    own = sigs.select("ordinal", F.col("ordinal").alias("label"))
    if marker == "all" and least:
        roles = settle(key_roles(sigs, plan), "roles")

        def step(labels: DataFrame) -> DataFrame:
            read = _before(roles.join(labels, "ordinal"), F.when(F.col("m"), F.col("label")), F.min, F.least, "read")
            return read.groupBy("ordinal").agg(F.least(F.min("label"), F.min(F.when(F.col("p"), F.col("read")))).alias("label"))

    else:
        if marker == "all":
            marks = role_keys(sigs, plan, "mark").select("key", F.col("ordinal").alias("parent"))
            edges = role_keys(sigs, plan, "probe").join(marks, "key").filter("parent < ordinal").select("ordinal", "parent").distinct()
        else:
            edges = parent_edges(sigs, plan, marker)
        edges = settle(edges, "parents")
        if not least:  # the greatest founder reachable: founders keep their own, others start at none
            founders = own.join(edges.select("ordinal").distinct(), "ordinal", "left_anti")
            own = own.join(founders.select("ordinal").withColumn("f", F.lit(True)), "ordinal", "left").select("ordinal", F.when(F.col("f"), F.col("label")).otherwise(0).alias("label"))

            def step(labels: DataFrame) -> DataFrame:
                up = edges.join(labels.select(F.col("ordinal").alias("parent"), F.col("label").alias("l")), "parent").groupBy("ordinal").agg(F.max("l").alias("l"))
                return labels.join(up, "ordinal", "left").select("ordinal", F.greatest("label", F.coalesce("l", "label")).alias("label"))

            labels, seen = settle(own, "labels"), None
            while (state := labels.agg(F.sum("label")).first()[0]) != seen:
                labels, seen = settle(step(labels), "labels"), state
            return sigs.join(labels, "ordinal").select(F.col("label").alias("cluster_id"), "ordinal", F.col("sig").alias("elements"))

        def step(labels: DataFrame) -> DataFrame:
            up = edges.join(labels.select(F.col("ordinal").alias("parent"), F.col("label").alias("l")), "parent").groupBy("ordinal").agg(agg("l").alias("l"))
            return labels.join(up, "ordinal", "left").select("ordinal", pick("label", F.coalesce("l", "label")).alias("label"))

    labels = _settle_labels(own, step)
    return sigs.join(labels, "ordinal").select(F.col("label").alias("cluster_id"), "ordinal", F.col("sig").alias("elements"))


def components(sigs: DataFrame, plan: OverlapPlan) -> DataFrame:
    """Merging on touch: connected components. A key that is written and read joins all its items, by a star."""
    roles = role_keys(sigs, plan, "mark").select("key", "ordinal", F.lit(1).alias("r")).union(role_keys(sigs, plan, "probe").select("key", "ordinal", F.lit(2).alias("r")))
    hubs = roles.groupBy("key").agg(F.min("ordinal").alias("hub"), F.max("ordinal").alias("top"), F.bit_or("r").alias("r")).filter("hub < top and r = 3").select("key", "hub")
    edges = roles.join(hubs, "key").filter("ordinal <> hub").select(F.col("ordinal").alias("a"), F.col("hub").alias("b")).distinct()
    labels = component_labels(edges)
    return sigs.join(labels.withColumnRenamed("node", "ordinal"), "ordinal", "left").select(F.coalesce("label", "ordinal").alias("cluster_id"), "ordinal", F.col("sig").alias("elements"))
