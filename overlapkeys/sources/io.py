"""Files: signature lines, three-column assignments, typed round trips, the key store."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from overlapkeys.operators.keys import role_keys
from overlapkeys.plans.overlap_plan import OverlapPlan

SCHEMA = "ordinal bigint, item_id bigint, size int, sig array<string>"


def write_signature_lines(sigs: DataFrame, path: str, sep: str = "-") -> None:
    """Numbered lines: arrival number, tab, elements joined by ``sep``; an element with ``sep`` in it is refused."""
    bad = F.exists("sig", lambda e: F.contains(e, F.lit(sep)) | F.contains(e, F.lit("\t")))
    line = F.concat_ws("\t", F.col("ordinal").cast("string"), F.array_join("sig", sep))
    sigs.select(F.when(bad, F.raise_error(F.lit("an element holds the separator")).cast("string")).otherwise(line).alias("value")).write.text(path)


def read_signature_lines(spark: SparkSession, path: str, sep: str = "-") -> DataFrame:
    parts = F.split("value", "\t")
    df = spark.read.text(path).select(parts[0].cast("bigint").alias("ordinal"), F.array_sort(F.array_distinct(F.split(parts[1], sep.replace("|", "\\|").replace(".", "\\.")))).alias("sig"))
    return df.select("ordinal", F.col("ordinal").alias("item_id"), F.size("sig").alias("size"), "sig")


def save_signatures(sigs: DataFrame, path: str, fmt: str = "parquet") -> None:
    if fmt == "csv":  # no arrays there
        sigs.withColumn("sig", F.to_json("sig")).write.option("header", True).option("escape", '"').csv(path)
    else:
        sigs.write.format(fmt).save(path)


def load_signatures(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    if fmt == "csv":
        df = spark.read.schema(SCHEMA.replace("array<string>", "string")).option("header", True).option("escape", '"').csv(path)
        return df.withColumn("sig", F.from_json("sig", "array<string>"))
    return spark.read.schema(SCHEMA).format(fmt).load(path)


def write_assignments(assigned: DataFrame, path: str, fmt: str = "csv") -> None:
    """Cluster id, arrival number, elements; sorted by ranges of arrival, so files follow each other."""
    rows = assigned.select("cluster_id", "ordinal", F.array_join("elements", "-").alias("elements"))
    rows.repartitionByRange("ordinal").sortWithinPartitions("ordinal").write.format(fmt).option("sep", "\t").save(path)


def read_assignments(spark: SparkSession, path: str) -> DataFrame:
    rows = spark.read.schema("cluster_id bigint, ordinal bigint, elements string").option("sep", "\t").csv(path)
    return rows.withColumn("elements", F.split("elements", "-"))


class KeyStore:
    """Leaders and their mark keys on disk. Keys are dealt to buckets by their hash and appended batch by batch:
    nothing written is made again, and a batch reads only the buckets that it probes.

    ``keep`` bounds how many batches back a marker counts; older ones have expired. None: markers stay.
    """

    KEYS = "key string, leader bigint, batch bigint, bucket int"
    LEADERS = "ordinal bigint, size int, sig array<string>, batch bigint"

    def __init__(self, spark: SparkSession, path: str, plan: OverlapPlan, buckets: int = 16, keep: int | None = None):
        self.spark, self.path, self.plan, self.buckets, self.keep = spark, path, plan, buckets, keep

    def _bucket(self) -> Column:
        return F.pmod(F.xxhash64("key"), F.lit(self.buckets)).cast("int")

    def _batches(self, part: str) -> list[int]:
        """Numbers of the batches written; a listing of one folder."""
        jvm = self.spark.sparkContext._jvm
        where = jvm.org.apache.hadoop.fs.Path(f"{self.path}/{part}")
        fs = where.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration())
        if not fs.exists(where):
            return []
        return sorted(int(f.getPath().getName().split("=")[1]) for f in fs.listStatus(where) if "=" in f.getPath().getName())

    def _live(self, part: str, before: int | None) -> list[str]:
        least = None if self.keep is None or before is None else before - self.keep
        return [f"{self.path}/{part}/batch={b}" for b in self._batches(part) if (before is None or b < before) and (least is None or b >= least)]

    def append(self, leaders: DataFrame, batch_id: int) -> None:
        """Idempotent by batch: writing a batch again replaces it."""
        keys = role_keys(leaders, self.plan, "mark").groupBy("key").agg(F.min("ordinal").alias("leader"))
        keys.withColumn("bucket", self._bucket()).repartition(self.buckets, "bucket").sortWithinPartitions("bucket", "key").write.mode("overwrite").partitionBy("bucket").parquet(f"{self.path}/keys/batch={batch_id}")
        leaders.select("ordinal", "size", "sig").write.mode("overwrite").parquet(f"{self.path}/leaders/batch={batch_id}")

    def next_batch(self) -> int:
        return max(self._batches("keys"), default=-1) + 1

    def probe(self, probes: DataFrame, before: int | None = None) -> DataFrame:
        """(ordinal, leader): the earliest stored leader of (key, ordinal) rows that has one."""
        paths = self._live("keys", before)
        none = self.spark.createDataFrame([], "ordinal bigint, leader bigint")
        if not paths:
            return none
        dealt = probes.select("key", "ordinal").withColumn("bucket", self._bucket())
        asked = [r["bucket"] for r in dealt.select("bucket").distinct().collect()]  # at most as many as buckets
        stored = self.spark.read.option("basePath", f"{self.path}/keys").schema(self.KEYS).parquet(*paths).filter(F.col("bucket").isin(asked))
        return dealt.join(stored.select("bucket", "key", "leader"), ["bucket", "key"]).groupBy("ordinal").agg(F.min("leader").alias("leader"))

    def leaders(self, before: int | None = None) -> DataFrame:
        paths = self._live("leaders", before)
        if not paths:
            return self.spark.createDataFrame([], "ordinal bigint, size int, sig array<string>")
        return self.spark.read.option("basePath", f"{self.path}/leaders").schema(self.LEADERS).parquet(*paths).select("ordinal", "size", "sig")
