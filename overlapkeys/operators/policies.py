"""Side effects and variants on top of the leader policy: hierarchies, splits, caps, refreshed centroids, weights."""

from __future__ import annotations

from fractions import Fraction

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from overlapkeys.plans.overlap_plan import OverlapPlan
from overlapkeys.plans.rules import SimilarityRule
from overlapkeys.session import settle

from .keys import encoded, expanded, mark_keys, probe_keys
from .leader import leader
from .retrieve import similar_pairs


def founders(sigs: DataFrame, plan: OverlapPlan) -> DataFrame:
    """Items without an earlier similar item."""
    first = mark_keys(sigs, plan).groupBy("key").agg(F.min("ordinal").alias("first"))
    late = probe_keys(sigs, plan).join(first, "key").filter("first < ordinal").select("ordinal").distinct()
    return sigs.join(late, "ordinal", "left_anti").select("ordinal")


def renumber_clusters(assigned: DataFrame) -> DataFrame:
    """Cluster ids 1..c in the order of founding; the clusters alone are sorted."""
    ids = assigned.select("cluster_id").distinct()
    sized = ids.withColumn("b", F.floor(F.col("cluster_id") / 65536))
    offsets = sized.groupBy("b").agg(F.count("*").alias("n"))
    offsets = offsets.select("b", (F.sum("n").over(W.orderBy("b")) - F.col("n")).alias("o"))
    numbered = sized.withColumn("r", F.row_number().over(W.partitionBy("b").orderBy("cluster_id"))).join(offsets, "b")
    return assigned.join(numbered.select("cluster_id", (F.col("r") + F.col("o")).cast("bigint").alias("number")), "cluster_id")


def split_oversize(assigned: DataFrame, sigs: DataFrame, stricter: OverlapPlan, max_size: int) -> DataFrame:
    """Clusters of over ``max_size`` items are clustered anew inside themselves at a stricter threshold."""
    big = settle(assigned.groupBy("cluster_id").count().filter(F.col("count") > max_size).select("cluster_id"), "big")
    inside = assigned.join(big, "cluster_id", "left_semi").select("ordinal", "cluster_id")
    # the cluster id joins the signature's elements in front, so only items of one cluster share keys
    rows = sigs.join(inside, "ordinal")
    pairs = _pairs_within(rows, stricter)
    again = _leaders_of_pairs(rows.select("ordinal"), pairs)
    kept = assigned.join(big, "cluster_id", "left_anti")
    return kept.union(again.join(sigs.select("ordinal", F.col("sig").alias("elements")), "ordinal").select("cluster_id", "ordinal", "elements"))


def _pairs_within(rows: DataFrame, plan: OverlapPlan) -> DataFrame:
    home = rows.select("ordinal", "cluster_id")
    marks = mark_keys(rows, plan).join(home, "ordinal").select("key", "cluster_id", F.col("ordinal").alias("earlier"))
    probes = probe_keys(rows, plan).join(home, "ordinal").select("key", "cluster_id", F.col("ordinal").alias("later"))
    return settle(probes.join(marks, ["key", "cluster_id"]).filter("earlier < later").select("earlier", "later").distinct(), "within")


def _leaders_of_pairs(items: DataFrame, pairs: DataFrame) -> DataFrame:
    """(ordinal, cluster_id) of the leader policy over given pairs."""
    state = settle(items.select("ordinal", F.lit(0).alias("s")), "state")
    while not state.filter("s = 0").isEmpty():
        seen = pairs.join(state.select(F.col("ordinal").alias("earlier"), "s"), "earlier").groupBy(F.col("later").alias("ordinal"))
        seen = seen.agg(F.max(F.col("s") == 1).alias("hit"), F.max(F.col("s") == 0).alias("held"))
        new = F.when(F.col("s") != 0, F.col("s")).when(F.col("hit"), 2).when(F.col("held"), 0).otherwise(1)
        state = settle(state.join(seen, "ordinal", "left").select("ordinal", new.cast("int").alias("s")), "state")
    led = state.filter("s = 1").select("ordinal")
    home = pairs.join(led.withColumnRenamed("ordinal", "earlier"), "earlier").groupBy(F.col("later").alias("ordinal")).agg(F.min("earlier").alias("cluster_id"))
    return home.join(led, "ordinal", "left_anti").union(led.select("ordinal", F.col("ordinal").alias("cluster_id")))


def capped_leader(sigs: DataFrame, plan: OverlapPlan, most: int) -> DataFrame:
    """At most ``most`` clusters: items of later ones stay unassigned (null)."""
    numbered = renumber_clusters(leader(sigs, plan))
    return numbered.select("ordinal", F.when(F.col("number") <= most, F.col("cluster_id")).alias("cluster_id"))


def hierarchy(sigs: DataFrame, thetas: list[str], sizes, mode: str = "independent") -> DataFrame:
    """(level, theta, ordinal, cluster_id) from the strictest threshold on; nested: a level clusters the leaders of the one before."""
    out, base, home = None, sigs, None
    for level, theta in enumerate(sorted(thetas, key=Fraction, reverse=True)):
        got = leader(base, OverlapPlan.build(SimilarityRule.jaccard(theta), sizes)).select("ordinal", "cluster_id")
        if mode == "nested":
            got = settle(got, "level")
            if home is not None:
                up = got.select(F.col("ordinal").alias("cluster_id"), F.col("cluster_id").alias("higher"))
                got = home.join(up, "cluster_id").select("ordinal", F.col("higher").alias("cluster_id"))
            home = settle(got, "level")
            got = home
            base = settle(sigs.join(home.filter("ordinal = cluster_id").select("ordinal"), "ordinal", "left_semi"), "base")
        part = got.select(F.lit(level).alias("level"), F.lit(theta).alias("theta"), "ordinal", "cluster_id")
        out = part if out is None else out.union(part)
    return out


def nesting_violations(levels: DataFrame) -> DataFrame:
    """(level, violations): clusters of a level whose items lie in several clusters of the next."""
    up = levels.select((F.col("level") - 1).alias("level"), "ordinal", F.col("cluster_id").alias("parent"))
    per = levels.join(up, ["level", "ordinal"]).groupBy("level", "cluster_id").agg(F.count_distinct("parent").alias("n"))
    return per.groupBy("level").agg(F.count_if(F.col("n") > 1).alias("violations"))


def element_counts(assigned: DataFrame) -> DataFrame:
    return assigned.select("cluster_id", F.explode("elements").alias("e")).groupBy("cluster_id", "e").agg(F.count("*").alias("n"))


def frequent_elements(counts: DataFrame, most: int = 10) -> DataFrame:
    """(cluster_id, sig): the most frequent elements of each cluster, ties by text."""
    top = counts.withColumn("r", F.row_number().over(W.partitionBy("cluster_id").orderBy(F.desc("n"), "e"))).filter(F.col("r") <= most)
    return top.groupBy("cluster_id").agg(F.array_sort(F.collect_list("e")).alias("sig"))


def leader_refreshed(sigs: DataFrame, plan: OverlapPlan, batch_rows: int) -> DataFrame:
    """After each batch a cluster's centroid becomes its most frequent elements; the next batch joins centroids or founds clusters.

    Only the counts of elements are carried on, so a batch costs what it brings and the clusters there are.
    """
    out, counts = None, None
    for start in range(0, sigs.agg(F.max("ordinal")).first()[0] or 0, batch_rows):
        batch = sigs.filter((F.col("ordinal") > start) & (F.col("ordinal") <= start + batch_rows))
        if counts is None:
            part = settle(leader(batch, plan), "part")
        else:
            centres = frequent_elements(counts, max(plan.sizes)).select(F.col("cluster_id").alias("ordinal"), F.size("sig").alias("size"), "sig")
            marks = mark_keys(centres, plan).groupBy("key").agg(F.min("ordinal").alias("cluster_id"))
            known = probe_keys(batch, plan).join(marks, "key").groupBy("ordinal").agg(F.min("cluster_id").alias("cluster_id"))
            known = settle(batch.join(known, "ordinal").select("cluster_id", "ordinal", F.col("sig").alias("elements")), "known")
            part = settle(known.union(leader(settle(batch.join(known, "ordinal", "left_anti"), "rest"), plan)), "part")
        fresh = element_counts(part)
        fresh = fresh if counts is None else counts.union(fresh).groupBy("cluster_id", "e").agg(F.sum("n").alias("n"))
        counts = settle(fresh, "counts")
        out = part if out is None else out.union(part)
    return out if out is not None else leader(sigs, plan)


# ---- named extensions: weights, degrees, probabilities ----
def weighted_pairs(weighted: DataFrame, theta: str) -> DataFrame:
    """Pairs with sum(min)/sum(max) >= theta over element weights (ordinal, weights map).

    The sum of the lesser weights is at most overlap * most, that of the greater ones at least union * least, so
    overlap / union >= theta * least / most: sub-signature keys at that lower threshold miss no pair. Totals and
    weights travel with the keys; the direct check decides.
    """
    t = Fraction(theta)
    total = F.aggregate(F.map_values("weights"), F.lit(0.0), lambda a, x: a + x)
    base = weighted.select("ordinal", "weights", total.alias("total"), F.array_sort(F.map_keys("weights")).alias("sig")).withColumn("size", F.size("sig"))
    base = settle(base.filter("size > 0"), "weighted")
    w = base.select("size", F.explode(F.map_values("weights")).alias("w"))
    low, high, sizes = w.agg(F.min("w"), F.max("w"), F.collect_set("size")).first()  # bounded by the cap on sizes
    if low is None or low <= 0:
        if low is None:
            return base.select(F.col("ordinal").alias("earlier"), F.col("ordinal").alias("later"), F.col("total").alias("score"))
        raise ValueError("weights must be above zero")
    safe = t * (Fraction(low) / Fraction(high)).limit_denominator(10_000) * Fraction(9999, 10_000)  # rounded down
    plan = OverlapPlan.build(SimilarityRule.jaccard(safe), sizes)

    def keyed(role: str, name: str) -> DataFrame:
        rows = expanded(base, plan, role)
        key = encoded(F.col("tag"), F.col("sub"), "text").alias("key")
        own = [F.col(c).alias(f"{name}_{c}") for c in ("ordinal", "sig", "weights", "total")]
        return rows.select(key, *own, *([F.col("sub")] if role == "probe" else []))

    met = keyed("probe", "b").join(keyed("mark", "a"), "key")
    met = met.filter((F.col("a_ordinal") < F.col("b_ordinal")) & (F.least("a_total", "b_total") >= F.greatest("a_total", "b_total") * float(t)))
    met = met.withColumn("both", F.array_intersect("a_sig", "b_sig")).filter(F.col("sub") == F.slice("both", 1, F.size("sub")))
    shared = F.aggregate("both", F.lit(0.0), lambda s, e: s + F.least(F.element_at("a_weights", e), F.element_at("b_weights", e)))
    scored = met.withColumn("low", shared).withColumn("score", F.col("low") / (F.col("a_total") + F.col("b_total") - F.col("low")))
    return scored.filter(F.col("score") >= float(t)).select(F.col("a_ordinal").alias("earlier"), F.col("b_ordinal").alias("later"), "score")


def fuzzy_membership(sigs: DataFrame, lo: str, hi: str, sizes) -> DataFrame:
    """(earlier, later, degree): 0 at the lower threshold, 1 at the upper one."""
    a, b = float(Fraction(lo)), float(Fraction(hi))
    pairs = similar_pairs(sigs, OverlapPlan.build(SimilarityRule.jaccard(lo), sizes))
    return pairs.select("earlier", "later", F.least(F.lit(1.0), F.greatest(F.lit(0.0), (F.col("score") - a) / (b - a))).alias("degree"))


def sampled_pairs(fuzzy: DataFrame, seed: int = 1) -> DataFrame:
    """Pairs kept with a probability equal to their degree, by a coin of the pair alone."""
    coin = ((F.col("earlier") * 7919 + F.col("later") * 104729 + seed) % 1000) / 1000.0
    return fuzzy.filter(coin < F.col("degree"))


def probabilistic_pairs(present: DataFrame, theta: str) -> DataFrame:
    """(ordinal, e, p) elements present with a probability: expected overlap over expected union >= theta."""
    t = float(Fraction(theta))
    mass = present.groupBy("ordinal").agg(F.sum("p").alias("mass"))
    full = present.join(mass, "ordinal")
    a = full.select("e", F.col("ordinal").alias("earlier"), F.col("p").alias("pa"), F.col("mass").alias("ma"))
    b = full.select("e", F.col("ordinal").alias("later"), F.col("p").alias("pb"), F.col("mass").alias("mb"))
    both = a.join(b, "e").filter("earlier < later").groupBy("earlier", "later", "ma", "mb").agg(F.sum(F.col("pa") * F.col("pb")).alias("o"))
    return both.withColumn("ratio", F.col("o") / (F.col("ma") + F.col("mb") - F.col("o"))).filter(F.col("ratio") >= t).select("earlier", "later", "ratio")


def soft_assign(multi: DataFrame) -> DataFrame:
    """Scores of an item's clusters as shares of one."""
    return multi.withColumn("share", F.col("score") / F.sum("score").over(W.partitionBy("ordinal"))).select("ordinal", "cluster_id", "share")
