"""Cost and accuracy measures over assignments, pairs and timing traces."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from overlapkeys.plans.overlap_plan import OverlapPlan
from overlapkeys.session import settle

from .keys import mark_keys, probe_keys
from .policies import founders


def size_histogram(assigned: DataFrame, log: bool = False) -> DataFrame:
    sizes = assigned.groupBy("cluster_id").agg(F.count("*").alias("members"))
    if log:
        return sizes.groupBy(F.floor(F.log2("members") + 1e-9).cast("bigint").alias("bin")).agg(F.count("*").alias("clusters"))
    return sizes.groupBy("members").agg(F.count("*").alias("clusters"))


def histogram_compare(a: DataFrame, b: DataFrame) -> DataFrame:
    """Share of clusters in each power-of-two bin, of two runs side by side."""

    def share(h: DataFrame, name: str) -> DataFrame:
        total = size_histogram(h, True).agg(F.sum("clusters").alias("n"))
        return size_histogram(h, True).crossJoin(F.broadcast(total)).select("bin", F.round(F.col("clusters") / F.col("n"), 6).alias(name))  # one row

    return share(a, "prefix_share").join(share(b, "full_share"), "bin", "full").select("bin", *[F.coalesce(c, F.lit(0.0)).alias(c) for c in ("prefix_share", "full_share")])


def identical(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: items whose cluster differs between two assignments, or that one lacks."""
    x, y = a.select("ordinal", F.col("cluster_id").alias("x")), b.select("ordinal", F.col("cluster_id").alias("y"))
    return x.join(y, "ordinal", "full").agg(F.count("*").alias("items"), F.count_if(~F.col("x").eqNullSafe(F.col("y"))).alias("mismatches"))


def pair_accuracy(found: DataFrame, truth: DataFrame) -> DataFrame:
    f = found.select("earlier", "later", F.lit(1).alias("f"))
    t = truth.select("earlier", "later", F.lit(1).alias("t"))
    n = f.join(t, ["earlier", "later"], "full").agg(F.count_if(F.expr("f = 1 and t = 1")).alias("tp"), F.count_if(F.expr("f = 1 and t is null")).alias("fp"), F.count_if(F.expr("f is null")).alias("fn"))
    return _ratios(n)


def class_accuracy(found: DataFrame, truth: DataFrame, members: DataFrame) -> DataFrame:
    """pair_accuracy of items from links of classes (marker, prober) under a symmetric rule that copies fulfil.

    A pair of classes stands for all pairs of their items, a class of n copies for n (n - 1) / 2 more: none is listed.
    Both kinds of links meet in one shuffle; the classes' sizes are written, so they are broadcast where they are few.
    """

    def sides(links: DataFrame, f: int) -> DataFrame:
        return links.select(F.least("marker", "prober").alias("a"), F.greatest("marker", "prober").alias("b"), F.lit(f).alias("f"), F.lit(1 - f).alias("t"))

    sizes = settle(members.groupBy("cls").agg(F.count("*").alias("n")), "sizes")
    met = sides(found, 1).union(sides(truth, 0)).groupBy("a", "b").agg(*[F.expr(f"nullif(max({c}), 0)").alias(c) for c in ("f", "t")])
    met = met.join(sizes.select(F.col("cls").alias("a"), F.col("n").alias("x")), "a").join(sizes.select(F.col("cls").alias("b"), F.col("n").alias("y")), "b")
    every = met.select("f", "t", (F.col("x") * F.col("y")).alias("n")).union(sizes.select(F.lit(1), F.lit(1), F.expr("n * (n - 1) div 2")))
    total = lambda test: F.coalesce(F.sum(F.when(F.expr(test), F.col("n"))), F.lit(0)).cast("bigint")
    return _ratios(every.agg(total("f = 1 and t = 1").alias("tp"), total("f = 1 and t is null").alias("fp"), total("f is null").alias("fn")))


def _ratios(n: DataFrame) -> DataFrame:
    ratio = lambda a, b: F.round(F.when(b > 0, a / b).otherwise(1.0), 6)
    return n.select("tp", "fp", "fn", ratio(F.col("tp"), F.col("tp") + F.col("fp")).alias("precision"), ratio(F.col("tp"), F.col("tp") + F.col("fn")).alias("recall"))


def adjusted_rand(a: DataFrame, b: DataFrame) -> DataFrame:
    """(ordinal, cluster_id) twice: agreement of pairs, adjusted for chance."""
    cell = a.select("ordinal", F.col("cluster_id").alias("x")).join(b.select("ordinal", F.col("cluster_id").alias("y")), "ordinal").groupBy("x", "y").agg(F.count("*").alias("n"))
    pairs = lambda df: df.agg(F.sum(F.col("n") * (F.col("n") - 1) / 2).alias("s"), F.sum("n").alias("t"))
    c, r, l = pairs(cell), pairs(cell.groupBy("x").agg(F.sum("n").alias("n"))), pairs(cell.groupBy("y").agg(F.sum("n").alias("n")))  # noqa: E741
    one = c.select(F.col("s").alias("c"), "t").crossJoin(r.select(F.col("s").alias("r"))).crossJoin(l.select(F.col("s").alias("l")))  # one row each
    want = F.col("r") * F.col("l") / (F.col("t") * (F.col("t") - 1) / 2)
    return one.select(F.round((F.col("c") - want) / ((F.col("r") + F.col("l")) / 2 - want), 6).alias("ari"))


def purity(assigned: DataFrame, labels: DataFrame) -> DataFrame:
    n = assigned.select("ordinal", "cluster_id").join(labels, "ordinal").groupBy("cluster_id", "label").agg(F.count("*").alias("n"))
    best = n.groupBy("cluster_id").agg(F.max("n").alias("m"), F.sum("n").alias("t"))
    return best.agg(F.round(F.sum("m") / F.sum("t"), 6).alias("purity"))


def top_clusters(assigned: DataFrame, texts: DataFrame, k: int) -> DataFrame:
    """The k largest clusters with the leader's text (ordinal, text)."""
    sizes = assigned.groupBy("cluster_id").agg(F.count("*").alias("members")).orderBy(F.desc("members"), "cluster_id").limit(k)
    return sizes.join(texts.withColumnRenamed("ordinal", "cluster_id"), "cluster_id")


def _scan_places(assigned: DataFrame) -> DataFrame:
    """(ordinal, cluster_id, present, place): leaders present when an item arrives, its own leader's place; founders counted by blocks."""
    lead = assigned.filter("cluster_id = ordinal").select("ordinal")
    dealt = assigned.select("ordinal", "cluster_id", F.floor(F.col("ordinal") / 65536).alias("b"))
    per = lead.groupBy(F.floor(F.col("ordinal") / 65536).alias("b")).agg(F.count("*").alias("n"))
    blocks = dealt.select("b").distinct().join(per, "b", "left").select("b", F.coalesce("n", F.lit(0)).alias("n"))
    before = blocks.select("b", (F.sum("n").over(W.orderBy("b")) - F.col("n")).alias("o"))
    is_lead = (F.col("cluster_id") == F.col("ordinal")).cast("bigint")
    inside = F.sum(is_lead).over(W.partitionBy("b").orderBy("ordinal")) - is_lead
    rank = dealt.withColumn("inside", inside).join(before, "b").select("ordinal", "cluster_id", (F.col("inside") + F.col("o")).alias("present"))
    return rank.join(rank.filter("ordinal = cluster_id").select(F.col("ordinal").alias("cluster_id"), (F.col("present") + 1).alias("place")), "cluster_id")


UNTIL = "case when ordinal = cluster_id then present else place end"  # comparisons of a scan that ends at the first match


def control_comparisons(assigned: DataFrame) -> DataFrame:
    """What a centroid scan would compare: all leaders present, or those up to the first match."""
    return _scan_places(assigned).agg(F.sum("present").alias("all_leaders"), F.sum(F.expr(UNTIL)).alias("until_match"))


def work_trace(assigned: DataFrame, sigs: DataFrame, plan: OverlapPlan, step: int) -> DataFrame:
    """(n, control, engine): work done after the first n arrivals, each ``step``, in operations.

    The control compares an arrival with the leaders up to its own; the engine looks up its probe keys and
    writes its mark keys if it leads.
    """
    counts = F.broadcast(plan.counts_df(sigs.sparkSession))  # one row a size
    each = _scan_places(assigned).join(sigs.select("ordinal", "size"), "ordinal").join(counts, "size")
    each = each.select(F.expr(f"(ordinal - 1) div {step}").alias("g"), F.expr(UNTIL).alias("control"), F.expr("probe_keys + if(ordinal = cluster_id, mark_keys, 0)").alias("engine"))
    per = each.groupBy("g").agg(F.count("*").alias("n"), F.sum("control").alias("control"), F.sum("engine").alias("engine"))
    run = W.orderBy("g")  # one row a step
    return per.select(*[F.sum(c).over(run).alias(c) for c in ("n", "control", "engine")])


def founder_growth(assigned: DataFrame, step: int) -> DataFrame:
    """(items, clusters): founders among the first items, each ``step``."""
    per = assigned.groupBy((F.expr(f"(ordinal - 1) div {step}") + 1).alias("g")).agg(F.count("*").alias("n"), F.count_if(F.col("cluster_id") == F.col("ordinal")).alias("f"))
    run = W.orderBy("g")  # one row a step
    return per.select(F.sum("n").over(run).alias("items"), F.sum("f").over(run).alias("clusters"))


def probe_stats(sigs: DataFrame, plan: OverlapPlan) -> DataFrame:
    first = mark_keys(sigs, plan).groupBy("key").agg(F.min("ordinal").alias("first"))
    n = probe_keys(sigs, plan).join(first, "key", "left").agg(F.count("*").alias("lookups"), F.count_if(F.expr("first < ordinal")).alias("hits"))
    fresh = founders(sigs, plan).agg(F.count("*").alias("new_items"))
    return n.crossJoin(fresh).select("lookups", "hits", F.round(F.col("hits") / F.col("lookups"), 6).alias("hit_rate"), "new_items")  # one row each


def store_size(sigs: DataFrame, plan: OverlapPlan) -> DataFrame:
    return mark_keys(sigs, plan).agg(F.count("*").alias("marker_rows"), F.count_distinct("key").alias("distinct_keys"))


def cost_by_decile(sigs: DataFrame, plan: OverlapPlan) -> DataFrame:
    """Mean probe keys an item by tenths of the arrivals: flat, as cost doesn't grow with items."""
    top = sigs.agg(F.max("ordinal").alias("top"))
    counts = F.broadcast(plan.counts_df(sigs.sparkSession))  # one row a size
    dealt = sigs.crossJoin(F.broadcast(top)).withColumn("decile", F.expr("(ordinal - 1) * 10 div top + 1")).join(counts, "size")  # one row
    return dealt.groupBy("decile").agg(F.count("*").alias("items"), F.round(F.avg("probe_keys"), 4).alias("mean_probe_keys"))


# ---- timing traces (run, n, elapsed_s) ----
def mean_time(trace: DataFrame) -> DataFrame:
    return trace.withColumn("mean_s", F.col("elapsed_s") / F.col("n"))


def marginal(trace: DataFrame) -> DataFrame:
    w = W.partitionBy("run").orderBy("n")
    dn, dt = F.col("n") - F.lag("n", 1, 0).over(w), F.col("elapsed_s") - F.lag("elapsed_s", 1, 0.0).over(w)
    return trace.withColumn("marginal_s", dt / dn)


def speedup(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select("n", F.col("elapsed_s").alias("a")).join(b.select("n", F.col("elapsed_s").alias("b")), "n").select("n", F.round(F.col("a") / F.col("b"), 6).alias("speedup"))


def extrapolate(trace: DataFrame, to: int, power: float = 2.0) -> DataFrame:
    return trace.select("run", F.lit(to).cast("bigint").alias("n"), (F.col("elapsed_s") * F.pow(F.lit(float(to)) / F.col("n"), F.lit(power))).alias("elapsed_s"))


def crossover(a: DataFrame, b: DataFrame) -> DataFrame:
    """The least n from which on b is faster than a at every later checkpoint; null if there is none."""
    both = a.select("n", F.col("elapsed_s").alias("a")).join(b.select("n", F.col("elapsed_s").alias("b")), "n")
    slower = both.agg(F.coalesce(F.max(F.when(F.col("b") >= F.col("a"), F.col("n"))), F.lit(0)).alias("until"))
    return both.crossJoin(F.broadcast(slower)).filter("n > until").agg(F.min("n").alias("crossover"))  # one row
