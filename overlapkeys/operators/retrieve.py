"""Exact retrieval: similar means sharing a key, so similarity search is an equi-join."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from overlapkeys.plans.overlap_plan import OverlapPlan
from overlapkeys.plans.rules import SimilarityRule
from overlapkeys.session import settle

from .keys import encoded, expanded, mark_keys, pair_tag_keys, probe_keys, role_keys


def verify(pairs: DataFrame, sigs: DataFrame, rule: SimilarityRule | None, other: DataFrame | None = None) -> DataFrame:
    """(earlier, later, overlap, score) of (earlier, later) pairs, those that the rule holds for; all if it is None."""
    a = sigs.select(F.col("ordinal").alias("earlier"), F.col("sig").alias("__a"))
    b = (sigs if other is None else other).select(F.col("ordinal").alias("later"), F.col("sig").alias("__b"))
    met = pairs.join(a, "earlier").join(b, "later")
    met = met.withColumn("overlap", F.size(F.array_intersect("__a", "__b")))
    # the item that probes comes first in a directed rule
    x, y = F.size("__b"), F.size("__a")
    if rule is not None:
        met = met.filter(rule.holds_col(F.col("overlap"), x, y))
    shown = rule or SimilarityRule.jaccard("1/2")
    return met.select("earlier", "later", "overlap", shown.score_col(F.col("overlap"), x, y).alias("score"))


def classes_of(sigs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(one row a distinct signature: ordinal of its first item, lo, hi, size, sig; membership: cls, ordinal).

    Written once: all that follows joins distinct signatures, so copies never meet in pairs of rows.
    """
    classes = sigs.groupBy("sig", "size").agg(F.min("ordinal").alias("ordinal"), F.max("ordinal").alias("hi"))
    classes = settle(classes.select("ordinal", F.col("ordinal").alias("lo"), "hi", "size", "sig"), "classes")
    members = sigs.select("ordinal", "sig").join(classes.select(F.col("ordinal").alias("cls"), "sig"), "sig").select("cls", "ordinal")
    return classes, members


def links_by(probes: DataFrame, marks: DataFrame, on: list[str], rule: SimilarityRule | None, once: Column) -> DataFrame:
    """(marker, prober, overlap, score) of classes that meet by ``on``: p_* and m_* rows with ordinal, lo or hi, and els.

    ``once`` holds at one of the keys that two classes share (it may use ``both``, their common elements, in order),
    so links need no distinct; the elements travel with the keys, so the rule needs no further join.
    """
    met = probes.join(marks, on).filter("p_ordinal <> m_ordinal and m_lo < p_hi")
    met = met.withColumn("both", F.array_intersect("p_els", "m_els")).filter(once)
    overlap, x, y = F.size("both"), F.size("p_els"), F.size("m_els")
    if rule is not None:
        met = met.filter(rule.holds_col(overlap, x, y))
    shown = rule or SimilarityRule.jaccard("1/2")
    return met.select(F.col("m_ordinal").alias("marker"), F.col("p_ordinal").alias("prober"), overlap.alias("overlap"), shown.score_col(overlap, x, y).alias("score"))


def side(classes: DataFrame, role: str, *more: str, els: str = "sig") -> DataFrame:
    """The columns of a class for one side of ``links_by``."""
    bound = "lo" if role == "m" else "hi"
    return classes.select(F.col("ordinal").alias(f"{role}_ordinal"), F.col(bound).alias(f"{role}_{bound}"), F.col(els).alias(f"{role}_els"), *more)


LISTED = 128  # items of a class in one row: Spark holds what two such rows make, before it hands on the first


def _packed(members: DataFrame) -> DataFrame:
    """(cls, ordinals): a class's items in rows of LISTED at most, rising."""
    place = F.row_number().over(W.partitionBy("cls").orderBy("ordinal"))
    part = F.floor((place - 1) / LISTED).alias("part")
    packed = members.select("cls", "ordinal", part).groupBy("cls", "part").agg(F.sort_array(F.collect_list("ordinal")).alias("ordinals"))
    return settle(packed.select("cls", "ordinals"), "packed")


def expand(links: DataFrame, classes: DataFrame, members: DataFrame, rule: SimilarityRule | None, digits: int | None = None) -> DataFrame:
    """(earlier, later, overlap, score) of items from links of classes, and of the copies inside a class.

    Links meet lists of items, so no row a pair is shuffled; scores are rounded to ``digits`` before pairs are listed.
    """
    size, shown = F.col("size"), rule or SimilarityRule.jaccard("1/2")
    copied = classes.filter("lo < hi and size > 0")
    if rule is not None:
        copied = copied.filter(rule.holds_col(size, size, size))
    copied = copied.select(F.col("ordinal").alias("marker"), F.col("ordinal").alias("prober"), size.alias("overlap"), shown.score_col(size, size, size).alias("score"))
    met = links.select("marker", "prober", "overlap", "score").union(copied)
    if digits is not None:
        met = met.withColumn("score", F.round("score", digits))
    packed = _packed(members)
    a, b = (packed.select(F.col("cls").alias(role), F.col("ordinals").alias(name)) for role, name in (("marker", "a"), ("prober", "b")))
    met = met.join(a, "marker").join(b, "prober").filter(F.element_at("a", 1) < F.element_at("b", -1))
    met = met.select(F.explode("a").alias("earlier"), "b", "overlap", "score").filter(F.col("earlier") < F.element_at("b", -1))
    return met.select("earlier", F.explode("b").alias("later"), "overlap", "score").filter("earlier < later")


def class_pairs(links: DataFrame, classes: DataFrame, members: DataFrame, rule: SimilarityRule | None) -> DataFrame:
    """(earlier, later, overlap, score): similar signatures by their first items, and each further copy with its first item.

    Under a symmetric rule that equal sets fulfil these rows hold every link; copies don't multiply.
    """
    across = links.filter("marker < prober").select(F.col("marker").alias("earlier"), F.col("prober").alias("later"), "overlap", "score")
    size, shown = F.col("size"), rule or SimilarityRule.jaccard("1/2")
    copies = members.filter("cls < ordinal").join(classes.select(F.col("ordinal").alias("cls"), "size"), "cls")
    return across.union(copies.select("cls", "ordinal", size, shown.score_col(size, size, size)))


def similar_classes(sigs: DataFrame, plan: OverlapPlan, encode: str = "text", hint: str | None = None) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(links of distinct signatures, their classes, membership): the whole join without listing copies."""
    classes, members = classes_of(sigs)
    probes = side(_with_keys(classes, plan, "probe", encode), "p", "key", "sub")
    marks = side(_with_keys(classes, plan, "mark", encode), "m", "key")
    if hint:
        marks = marks.hint(hint)
    # of the keys that two classes share, the one of their first common elements counts
    first = F.col("sub") == F.slice("both", 1, F.size("sub"))
    links = links_by(probes, marks, ["key"], plan.rule, first)
    return (links.distinct() if encode == "hash" else links), classes, members  # hashes may meet once more by chance


def _with_keys(classes: DataFrame, plan: OverlapPlan, role: str, encode: str) -> DataFrame:
    got = expanded(classes, plan, role)
    return got.withColumn("key", encoded(F.col("tag"), F.col("sub"), encode))


def similar_pairs(sigs: DataFrame, plan: OverlapPlan, encode: str = "text", hint: str | None = None) -> DataFrame:
    """Pairs of an earlier and a later similar item; the rule is checked on what travels with the keys."""
    links, classes, members = similar_classes(sigs, plan, encode, hint)
    return expand(links, classes, members, plan.rule)


def pairs_by_size_pair(sigs: DataFrame, plan: OverlapPlan) -> DataFrame:
    """One key list for both roles; pairs whose sizes aren't the key's two are left out."""
    keys = pair_tag_keys(sigs, plan)
    a = keys.select("key", "lo", "hi", F.col("ordinal").alias("earlier"), F.col("size").alias("x"))
    b = keys.select("key", F.col("ordinal").alias("later"), F.col("size").alias("y"))
    met = a.join(b, "key").filter("earlier < later and least(x, y) = lo and greatest(x, y) = hi")
    return verify(met.select("earlier", "later").distinct(), sigs, plan.rule)


def similarity_join(r: DataFrame, s: DataFrame, plan: OverlapPlan, how: str = "inner") -> DataFrame:
    """Rows of r with similar rows of s: (r_ordinal, s_ordinal), or rows of r for semi and anti."""
    probes = probe_keys(r, plan).select("key", F.col("ordinal").alias("r_ordinal"))
    marks = mark_keys(s, plan).select("key", F.col("ordinal").alias("s_ordinal"))
    pairs = probes.join(marks, "key").select("r_ordinal", "s_ordinal").distinct()
    if how == "inner":
        return pairs
    if how == "left":
        return r.select(F.col("ordinal").alias("r_ordinal")).join(pairs, "r_ordinal", "left")
    known = probes.join(marks.select("key"), "key", "left_semi").select(F.col("r_ordinal").alias("ordinal")).distinct()
    return r.join(known, "ordinal", "left_semi" if how == "semi" else "left_anti")


def is_known(sigs: DataFrame, store: DataFrame, plan: OverlapPlan) -> DataFrame:
    """(ordinal, known): whether a stored mark is similar."""
    hit = probe_keys(sigs, plan).join(store.select("key"), "key", "left_semi").select("ordinal").distinct().withColumn("hit", F.lit(True))
    return sigs.select("ordinal").join(hit, "ordinal", "left").select("ordinal", F.coalesce("hit", F.lit(False)).alias("known"))


def simple_classes(sigs: DataFrame, plan: OverlapPlan, verified: bool = False) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(links of distinct signatures that share a key without a size, their classes, membership)."""
    classes, members = classes_of(sigs.filter(F.col("size").isin(*plan.sizes)))  # others have no keys
    keys = expanded(classes, plan, "simple").withColumn("key", encoded(F.lit(0), F.col("sub"), "text"))
    # two sizes share the key sizes that both write; a pair counts at the least of them, with its first common elements
    least = {(x, y): min(set(plan.overlap_sizes(x)) & set(plan.overlap_sizes(y)), default=0) for x in plan.sizes for y in plan.sizes}
    of_sizes = F.create_map(*[F.lit(v) for (x, y), m in least.items() for v in (x * 1000 + y, m)])
    first = (F.size("sub") == of_sizes[F.size("p_els") * 1000 + F.size("m_els")]) & (F.col("sub") == F.slice("both", 1, F.size("sub")))
    return links_by(side(keys, "p", "key", "sub"), side(keys, "m", "key"), ["key"], plan.rule if verified else None, first), classes, members


def simple_candidates(sigs: DataFrame, plan: OverlapPlan) -> DataFrame:
    """Pairs that share a key without a size: false matches among them, none missing."""
    return expand(*simple_classes(sigs, plan), None)


def simple_verified(sigs: DataFrame, plan: OverlapPlan, digits: int | None = None) -> DataFrame:
    return expand(*simple_classes(sigs, plan, True), plan.rule, digits)


def false_matches(sigs: DataFrame, plan: OverlapPlan, digits: int | None = None) -> DataFrame:
    """Pairs that share a key without a size, but aren't similar: told by classes, before items are listed."""
    (links, classes, members), true = simple_classes(sigs, plan), similar_classes(sigs, plan)[0]
    size = F.col("size")
    apart = classes.filter(~plan.rule.holds_col(size, size, size))  # whose copies aren't similar either
    return expand(links.join(true.select("marker", "prober"), ["marker", "prober"], "left_anti"), apart, members, None, digits)


def neighbours(sigs: DataFrame, plan: OverlapPlan, item: int, k: int) -> DataFrame:
    """The k items most similar to one item; its keys alone are looked up."""
    one = sigs.filter(F.col("ordinal") == item)
    pairs = probe_keys(one, plan).select("key", F.col("ordinal").alias("later"))
    pairs = mark_keys(sigs, plan).select("key", F.col("ordinal").alias("earlier")).join(F.broadcast(pairs), "key")  # one item's keys
    found = verify(pairs.filter("earlier <> later").select("earlier", "later").distinct(), sigs, plan.rule)
    return found.select(F.col("earlier").alias("ordinal"), "overlap", "score").orderBy(F.desc("score"), "ordinal").limit(k)


def build_store(sigs: DataFrame, plan: OverlapPlan, marker: str = "flag", clusters: DataFrame | None = None) -> DataFrame:
    """Key table with its markers: a flag, the writer's cluster, its signature, or its ordinal."""
    keys = role_keys(sigs, plan, "mark", with_sig=True)
    if marker == "flag":
        return keys.select("key").distinct().withColumn("marker", F.lit(True))
    if marker == "signature":
        return keys.select("key", F.array_join("sig", "-").alias("marker"))
    if marker == "cluster":
        return keys.join(clusters.select("ordinal", "cluster_id"), "ordinal").groupBy("key").agg(F.min("cluster_id").alias("marker"))
    if marker == "key":
        return keys.groupBy("key").agg(F.min("ordinal").alias("marker"))
    raise ValueError(marker)


def match_witness(sigs: DataFrame, plan: OverlapPlan) -> DataFrame:
    """(earlier, later, witness): the elements that the pair shares."""
    pairs = similar_pairs(sigs, plan).select("earlier", "later")
    a = sigs.select(F.col("ordinal").alias("earlier"), F.col("sig").alias("a"))
    b = sigs.select(F.col("ordinal").alias("later"), F.col("sig").alias("b"))
    return pairs.join(a, "earlier").join(b, "later").select("earlier", "later", F.array_join(F.array_sort(F.array_intersect("a", "b")), "-").alias("witness"))
