"""What the training-data operators share: table access, materialising, ordering."""

from __future__ import annotations

import ctypes
import functools
import gc
from bisect import bisect_right
from collections.abc import Callable, Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from overlapkeys.session import drop, scratch, settle, sweep  # noqa: F401


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def give_back() -> None:
    """Return to the system what this process has freed and its allocators keep."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # only one C library has it
    if trim is not None:
        trim(0)


def lean(run: Callable[[Iterator], Iterator]) -> Callable[[Iterator], Iterator]:
    """``run`` over a task's batches; its worker, which waits for other stages' tasks, gives back what it has freed."""

    @functools.wraps(run)
    def task(batches: Iterator) -> Iterator:
        try:
            yield from run(batches)
        finally:
            give_back()

    return task


NO_ID = -(1 << 63)  # stands for a null id in Python, where nulls would make numbers of a column floats


def filled_id(name: str = "doc_id") -> F.Column:
    return F.coalesce(F.col(name).cast("long"), F.lit(NO_ID)).alias(name)


def unfilled(df: DataFrame, name: str = "doc_id") -> DataFrame:
    return df.withColumn(name, F.when(F.col(name) != NO_ID, F.col(name)))


def arrow_rows(spark: SparkSession, rows: int) -> None:
    """Rows of an Arrow batch in plans made from now on: few where whole texts go to Python and back, for memory."""
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", rows)


def key_of(text: str = "text") -> F.Column:
    """Second part of a document's key: equal doc_ids with other texts stay apart, null texts are empty."""
    return F.xxhash64(F.coalesce(F.col(text), F.lit("")))


HOT_SHARE = 10_000  # a key with more than one row in so many is hot; there are fewer than so many of them


def join_by_share(rows: DataFrame, told: DataFrame, keys: list[str], total: int) -> DataFrame:
    """Inner join of ``rows`` with ``told`` (one row a key; its column ``n`` counts the key's rows of ``rows``).

    Of ``total`` rows fewer than HOT_SHARE keys can have over 1 / HOT_SHARE each. These are broadcast, so
    their rows stay where they are; only rows of the other keys are shuffled. Read from settled tables.
    """
    least = total // HOT_SHARE
    hot, cold = told.filter(F.col("n") > least).drop("n"), told.filter(F.col("n") <= least).drop("n")
    near = rows.join(F.broadcast(hot), keys)
    far = rows.join(F.broadcast(hot.select(*keys)), keys, "left_anti").join(cold, keys)
    return near.unionByName(far)


def in_told(rows: DataFrame, told: DataFrame, key: str, by: list[str], total: int, salts: int = 64) -> DataFrame:
    """Rows whose ``key`` is in ``told`` (one row a key, with ``n`` as in join_by_share), each made only once.

    For rows that cost too much to make twice: those of hot keys are dealt to ``salts`` partitions by a
    hash of ``by``, so a task that is run again deals them alike.
    """
    least = total // HOT_SHARE
    hot = told.filter(F.col("n") > least).select(key, F.lit(True).alias("__hot"))
    salt = F.when(F.col("__hot"), F.pmod(F.xxhash64(*by), F.lit(salts)).cast("int")).otherwise(F.lit(0))
    dealt = rows.join(F.broadcast(hot), key, "left").withColumn("__salt", salt).drop("__hot")
    spread = F.when(F.col("n") > least, F.sequence(F.lit(0), F.lit(salts - 1))).otherwise(F.array(F.lit(0)))
    return dealt.join(told.select(key, F.explode(spread).alias("__salt")), [key, "__salt"], "left_semi").drop("__salt")


def with_next(df: DataFrame, order: str, value: str, to: str) -> DataFrame:
    """Each row with ``value`` of the row that has the next lower ``order``; the last row gets the first's.

    Rows of one ``order`` follow each other by a hash of ``value``, a null ``order`` (a long) comes last, ``value``
    has no nulls. The order is found on the ids alone: their ranges, a few for each shuffle partition, are blocks of
    about equal numbers of rows however ids are spread. ``lead`` runs inside a block, and a block's last row meets
    the first one of the block that follows.
    """
    spark, names = df.sparkSession, df.columns
    keyed = df.withColumn("__o", F.coalesce(order, F.lit(-(1 << 63)))).withColumn("__t", F.xxhash64(value))
    falling = [F.col("__o").desc(), F.col("__t")]
    ranges = 4 * int(spark.conf.get("spark.sql.shuffle.partitions"))
    ids = keyed.select("__o", "__t").repartitionByRange(ranges, *falling)
    ids = settle(ids.groupBy(F.spark_partition_id().alias("p")).agg(F.min(F.struct(F.bitwise_not("__o").alias("o"), F.col("__t").alias("t"))).alias("m")), "ranges")
    bounds = sorted((r["m"]["o"], r["m"]["t"]) for r in ids.collect())  # one row a range
    n = max(1, len(bounds))

    @F.pandas_udf("struct<b: int, head: boolean>")
    def dealt_to(o: pd.Series, t: pd.Series) -> pd.DataFrame:
        keys = list(zip((~o.to_numpy()).tolist(), t.tolist()))
        b = [bisect_right(bounds, k) - 1 for k in keys]
        return pd.DataFrame({"b": b, "head": [k == bounds[i] for k, i in zip(keys, b)]})

    dealt = keyed.withColumn("__r", dealt_to("__o", "__t")).withColumn("__b", F.col("__r.b")).withColumn("__head", F.col("__r.head")).drop("__r")
    inner = dealt.withColumn("__n", F.lead(value).over(W.partitionBy("__b").orderBy(*falling)))
    heads = dealt.filter("__head").groupBy("__b").agg(F.first(value).alias("__h"))  # rows of one key have one value
    heads = heads.select(F.pmod(F.col("__b") - 1, F.lit(n)).alias("__b"), "__h")
    return inner.join(heads, "__b", "left").withColumn(to, F.coalesce("__n", "__h")).select(*names, to)
