"""Sub-signature keys by built-in expressions: broadcast plan, explode, pick positions. No shuffle, no Python."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from overlapkeys.plans.overlap_plan import OverlapPlan

SEPARATOR = "\u001f"


def encoded(tag: Column, sub: Column, encode: str) -> Column:
    if encode == "text":
        return F.concat_ws(SEPARATOR, tag.cast("string"), F.array_join(sub, SEPARATOR))
    if encode == "hash":
        return F.xxhash64(tag, F.array_join(sub, SEPARATOR))
    if encode == "struct":
        return F.struct(tag.alias("tag"), sub.alias("sub"))
    raise ValueError(encode)


def expanded(sigs: DataFrame, plan: OverlapPlan, role: str) -> DataFrame:
    """Each row with tag and sub for each combination that ``role`` asks for."""
    table = F.broadcast(plan.to_df(sigs.sparkSession, role).select("size", "plan"))  # bounded by PLAN_LIMIT
    rows = sigs.join(table, "size").select(*sigs.columns, F.explode("plan").alias("__p"))
    return rows.select(*sigs.columns, F.col("__p.tag").alias("tag"), F.transform("__p.pos", lambda i: F.element_at(F.col("sig"), i)).alias("sub"))


def sub_signatures(sigs: DataFrame, plan: OverlapPlan) -> DataFrame:
    return expanded(sigs.select("ordinal", "size", "sig"), plan, "simple").select("ordinal", F.array_join("sub", SEPARATOR).alias("sub"))


def role_keys(sigs: DataFrame, plan: OverlapPlan, role: str, encode: str = "text", with_sig: bool = False) -> DataFrame:
    """(ordinal, tag, key): what an item writes (mark), looks up (probe), either without sizes (simple), or both (pair)."""
    got = expanded(sigs.select("ordinal", "size", "sig"), plan, role)
    return got.select("ordinal", *(["size", "sig"] if with_sig else []), "tag", encoded(F.col("tag"), F.col("sub"), encode).alias("key"))


def simple_keys(sigs: DataFrame, plan: OverlapPlan, encode: str = "text") -> DataFrame:
    return role_keys(sigs, plan, "simple", encode).drop("tag")


def mark_keys(sigs: DataFrame, plan: OverlapPlan, encode: str = "text") -> DataFrame:
    return role_keys(sigs, plan, "mark", encode)


def probe_keys(sigs: DataFrame, plan: OverlapPlan, encode: str = "text") -> DataFrame:
    return role_keys(sigs, plan, "probe", encode)


def pair_tag_keys(sigs: DataFrame, plan: OverlapPlan, encode: str = "text") -> DataFrame:
    got = role_keys(sigs, plan, "pair", encode, with_sig=True)
    return got.select("ordinal", "size", F.expr("tag div 1000").cast("int").alias("lo"), (F.col("tag") % 1000).alias("hi"), "key")


def element_codes(sigs: DataFrame) -> DataFrame:
    """(text, code, df): codes by falling frequency, then text; numbered by blocks of frequency, no global sort of elements."""
    df = sigs.select(F.explode("sig").alias("text")).groupBy("text").agg(F.count("*").alias("df"))
    sizes = df.groupBy("df").agg(F.count("*").alias("n"))
    offset = sizes.select("df", (F.sum("n").over(W.orderBy(F.desc("df"))) - F.col("n")).alias("o"))  # one row a frequency
    inside = df.withColumn("r", F.row_number().over(W.partitionBy("df").orderBy("text")))
    return inside.join(offset, "df").select("text", (F.col("o") + F.col("r")).cast("bigint").alias("code"), "df")


def encode_elements(sigs: DataFrame) -> DataFrame:
    """(ordinal, codes array<bigint>) in place of texts."""
    flat = sigs.select("ordinal", F.explode("sig").alias("text")).join(element_codes(sigs).select("text", "code"), "text")
    return flat.groupBy("ordinal").agg(F.array_sort(F.collect_list("code")).alias("codes"))


def collapse_identical(sigs: DataFrame) -> DataFrame:
    """One row a distinct signature: its first ordinal and how many have it."""
    return sigs.groupBy("sig", "size").agg(F.min("ordinal").alias("ordinal"), F.count("*").alias("members"))


def key_volume(sigs: DataFrame, plan: OverlapPlan) -> DataFrame:
    counts = F.broadcast(plan.counts_df(sigs.sparkSession))  # one row a size
    per = sigs.groupBy("size").agg(F.count("*").alias("items")).join(counts, "size")
    return per.select("size", "items", (F.col("items") * F.col("mark_keys")).alias("mark_rows"), (F.col("items") * F.col("probe_keys")).alias("probe_rows"))
