"""Signature tables (ordinal, item_id, size, sig) from the given tables, and rules of admission."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from overlapkeys.session import settle

SEPARATOR = "\u001f"
WORD_BREAK = "[^a-z0-9À-ÿ]+"


def canonical(elements: Column) -> Column:
    """Sorted, distinct, without nulls: one form for each set."""
    return F.array_sort(F.array_distinct(F.array_compact(elements)))


def with_ordinal(df: DataFrame, block: Column, *order: str) -> DataFrame:
    """Dense arrival numbers from 1, without a global sort: rank inside a block plus the blocks before.

    ``block`` must rise with the order; only one row a block passes the unpartitioned window.
    """
    dealt = df.withColumn("__b", block)
    sizes = dealt.groupBy("__b").agg(F.count("*").alias("__n"))
    offsets = sizes.select("__b", (F.sum("__n").over(W.orderBy("__b")) - F.col("__n")).alias("__o"))
    ranked = dealt.withColumn("__r", F.row_number().over(W.partitionBy("__b").orderBy(*order)))
    joined = ranked.join(offsets, "__b")
    return joined.withColumn("ordinal", (F.col("__r") + F.col("__o")).cast("bigint")).drop("__b", "__r", "__o")


def admit(df: DataFrame, sizes, out_of_range: str = "error") -> DataFrame:
    """Rows (.., sig) with a size in ``sizes``; others raise, go, or become an empty signature of their own cluster."""
    allowed = list(map(int, sizes))
    sized = df.withColumn("size", F.coalesce(F.size("sig"), F.lit(0)))
    inside = F.col("size").isin(allowed)
    if out_of_range == "drop":
        return sized.filter(inside)
    if out_of_range == "singleton":
        return sized.withColumn("sig", F.when(inside, F.col("sig")).otherwise(F.array().cast("array<string>"))).withColumn("size", F.when(inside, F.col("size")).otherwise(0))
    bad = F.raise_error(F.concat(F.lit("signature size not allowed: "), F.col("size").cast("string")))
    return sized.withColumn("size", F.when(inside, F.col("size")).otherwise(bad.cast("int")))


def cap(df: DataFrame, most: int = 10, by: str = "tail", weights: str | None = None) -> DataFrame:
    """At most ``most`` elements: the tail of the sorted list goes, or the least weights."""
    if by == "tail":
        return df.withColumn("sig", F.slice("sig", 1, most))
    ranked = F.sort_array(F.transform(F.map_entries(weights), lambda e: F.struct((-e["value"]).alias("w"), e["key"].alias("e"))))
    return df.withColumn("sig", F.array_sort(F.transform(F.slice(ranked, 1, most), lambda x: x["e"])))


def pseudonymize(df: DataFrame, key: str = "k") -> DataFrame:
    """Each element becomes a digest string of its own; matches stay."""
    return df.withColumn("sig", F.array_sort(F.transform("sig", lambda e: F.substring(F.sha2(F.concat(F.lit(key), e), 256), 1, 16))))


def inline_signatures(spark: SparkSession, texts: list[str]) -> DataFrame:
    rows = [(k, k, len(set(t)), sorted(set(t))) for k, t in enumerate(texts, 1)]
    return spark.createDataFrame(rows, "ordinal bigint, item_id bigint, size int, sig array<string>")


def keyword_signatures(tokens: DataFrame, total: DataFrame, most: int = 10, df_lo: int = 2, df_floor: int = 0) -> DataFrame:
    """(item_id, sig) of the best tokens of (item_id, token): tf falling, df rising, token rising.

    ``total`` has one row, n; tokens in fewer than ``df_lo`` or more than max(df_floor, n div 10) items go.
    """
    tf = tokens.groupBy("item_id", "token").agg(F.count("*").alias("tf"))  # rows of an item already lie together
    tf = settle(tf, "counts")  # splitting texts costs most: once, not for the frequencies and the ranks
    df = tf.groupBy("token").agg(F.count("*").alias("df"))
    kept = df.crossJoin(F.broadcast(total)).filter((F.col("df") >= df_lo) & (F.col("df") <= F.greatest(F.expr("n div 10"), F.lit(df_floor)))).select("token", "df")
    kept = settle(kept, "words")  # its size is known then: it is broadcast only where it is small
    best = W.partitionBy("item_id").orderBy(F.desc("tf"), "df", "token")
    top = tf.join(kept, "token").withColumn("r", F.row_number().over(best)).filter(F.col("r") <= most)
    return top.groupBy("item_id").agg(F.array_sort(F.collect_list("token")).alias("sig"))


def _finish(df: DataFrame, least: int = 2, most: int = 10, block: Column | None = None, order: tuple[str, ...] = ("item_id",)) -> DataFrame:
    sized = df.withColumn("sig", F.slice("sig", 1, most)).withColumn("size", F.size("sig")).filter(F.col("size") >= least)
    block = F.floor(F.col("item_id") / 65536) if block is None else block
    return with_ordinal(sized, block, *order).select("ordinal", "item_id", "size", "sig")


def _tokens(df: DataFrame, item: str, text: Column) -> DataFrame:
    """(item_id, token). Texts are dealt by item before they are split, so tokens are counted and ranked where they are.

    The number of partitions is given, or few would be left of texts that are small until they are split.
    """
    parts = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = df.select(F.col(item).cast("bigint").alias("item_id"), text.alias("text")).repartition(parts, "item_id")
    return dealt.select("item_id", F.explode(F.split(F.lower("text"), WORD_BREAK)).alias("token")).filter(F.length("token") >= 4)


def load(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def sig_documents(spark: SparkSession, d: str) -> DataFrame:
    docs = load(spark, d, "documents", "doc_id", "text")
    return _finish(keyword_signatures(_tokens(docs, "doc_id", F.col("text")), docs.agg(F.count("*").alias("n"))))


def sig_orders(spark: SparkSession, d: str) -> DataFrame:
    lines, part = load(spark, d, "lineitem", "l_orderkey", "l_partkey"), load(spark, d, "part", "p_partkey", "p_brand")
    brands = lines.join(part, F.col("l_partkey") == F.col("p_partkey"))
    return _finish(brands.groupBy(F.col("l_orderkey").cast("bigint").alias("item_id")).agg(F.array_sort(F.collect_set("p_brand")).alias("sig")))


def sig_suppliers_of_order(spark: SparkSession, d: str) -> DataFrame:
    lines = load(spark, d, "lineitem", "l_orderkey", "l_suppkey")
    return _finish(lines.groupBy(F.col("l_orderkey").cast("bigint").alias("item_id")).agg(F.array_sort(F.collect_set(F.col("l_suppkey").cast("string"))).alias("sig")))


def event_elements(events: DataFrame) -> DataFrame:
    bucket = F.expr("cast(get_json_object(props, '$.k') as int) div 20")
    return events.select(F.to_date("ts").alias("day"), F.col("user_id").cast("bigint").alias("item_id"), F.concat_ws(":", "event_type", bucket.cast("string")).alias("element"))


def sig_userday(spark: SparkSession, d: str) -> DataFrame:
    events = event_elements(load(spark, d, "events", "ts", "user_id", "event_type", "props"))
    days = events.groupBy("day", "item_id").agg(F.array_sort(F.collect_set("element")).alias("sig"))
    days = settle(days, "days")  # ordinals need sizes of blocks and ranks inside: events are read once for both
    return _finish(days, block=F.unix_date("day"), order=("day", "item_id"))


def sig_part(spark: SparkSession, d: str) -> DataFrame:
    part = load(spark, d, "part", "p_partkey", "p_name", "p_brand", "p_type", "p_size")
    elements = F.concat(F.split("p_name", " "), F.array("p_brand", "p_type", F.expr("concat('sz', p_size div 10)")))
    return _finish(part.select(F.col("p_partkey").cast("bigint").alias("item_id"), canonical(elements).alias("sig")))


def _with_nation(spark: SparkSession, d: str, df: DataFrame, key: str) -> DataFrame:
    return df.join(F.broadcast(load(spark, d, "nation", "n_nationkey", "n_regionkey")), F.col(key) == F.col("n_nationkey"))  # one row a nation


def sig_customer(spark: SparkSession, d: str) -> DataFrame:
    c = _with_nation(spark, d, load(spark, d, "customer", "c_custkey", "c_nationkey", "c_mktsegment", "c_acctbal"), "c_nationkey")
    e = F.expr("array(concat('N', n_nationkey), concat('R', n_regionkey), c_mktsegment, concat('B', cast(floor(c_acctbal / 1000) as int)))")
    return _finish(c.select(F.col("c_custkey").cast("bigint").alias("item_id"), canonical(e).alias("sig")))


def sig_supplier(spark: SparkSession, d: str) -> DataFrame:
    s = _with_nation(spark, d, load(spark, d, "supplier", "s_suppkey", "s_nationkey", "s_acctbal"), "s_nationkey")
    e = F.expr("array(concat('N', n_nationkey), concat('R', n_regionkey), concat('B', cast(floor(s_acctbal / 2000) as int)))")
    return _finish(s.select(F.col("s_suppkey").cast("bigint").alias("item_id"), canonical(e).alias("sig")))


def sig_embeddings(spark: SparkSession, d: str) -> DataFrame:
    e = load(spark, d, "embeddings", "vec_id", "embedding")
    block = "concat('b', b, '.', cast(array_position(slice(embedding, b * 8 + 1, 8), array_max(slice(embedding, b * 8 + 1, 8))) - 1 as int))"
    return _finish(e.select(F.col("vec_id").cast("bigint").alias("item_id"), canonical(F.expr(f"transform(sequence(0, 7), b -> {block})")).alias("sig")))


def sig_pages(spark: SparkSession, d: str) -> DataFrame:
    pages = load(spark, d, "pages", "page_id", "html")
    text = F.regexp_replace(F.regexp_replace("html", "(?s)<(script|style)[^>]*>.*?</(script|style)>", " "), "<[^>]*>", " ")
    return _finish(keyword_signatures(_tokens(pages, "page_id", text), pages.agg(F.count("*").alias("n")), df_floor=2))


def sig_conversations(spark: SparkSession, d: str) -> DataFrame:
    turns = load(spark, d, "conversations", "conv_id", "text")
    return _finish(keyword_signatures(_tokens(turns, "conv_id", F.col("text")), turns.agg(F.count_distinct("conv_id").alias("n"))))


def weighted_orders(spark: SparkSession, d: str) -> DataFrame:
    """(ordinal, weights) quantity of each brand of an order."""
    lines, part = load(spark, d, "lineitem", "l_orderkey", "l_partkey", "l_quantity"), load(spark, d, "part", "p_partkey", "p_brand")
    q = lines.join(part, F.col("l_partkey") == F.col("p_partkey")).groupBy("l_orderkey", "p_brand").agg(F.sum("l_quantity").alias("w"))
    m = q.groupBy(F.col("l_orderkey").cast("bigint").alias("ordinal")).agg(F.map_from_entries(F.collect_list(F.struct("p_brand", "w"))).alias("weights"))
    return m.filter(F.size("weights").between(2, 10))
