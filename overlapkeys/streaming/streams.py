"""Streams: leader clustering by batches with a key store, similar pairs, windowed signatures, replay removal.

``events.ts`` is a timestamp without zone, which watermarks refuse; it is cast in a UTC session.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

from overlapkeys.operators.keys import mark_keys, probe_keys
from overlapkeys.operators.leader import leader_step
from overlapkeys.plans.overlap_plan import OverlapPlan
from overlapkeys.plans.rules import SimilarityRule
from overlapkeys.session import scratch, settle
from overlapkeys.sources.io import KeyStore
from overlapkeys.sources.signatures import sig_userday, with_ordinal

SIGNATURE = "ordinal bigint, item_id bigint, size int, sig array<string>"


def stream_signatures(spark: SparkSession, path: str, files: int = 1) -> DataFrame:
    return spark.readStream.schema(SIGNATURE).option("maxFilesPerTrigger", files).parquet(path)


def _numbered(batch: DataFrame, path: str, batch_id: int, order: list[str]) -> DataFrame:
    """Rows with their arrival numbers: the rows of earlier batches, as written beside the result, plus the rank in this one.

    The rank is built from ranges of rows, so no window holds the whole batch; one row a range passes the last one.
    """
    spark = batch.sparkSession
    base = 0
    if batch_id:
        counts = spark.read.schema("n bigint, batch bigint").option("basePath", path).parquet(f"{path}/batch=*")
        base = counts.filter(F.col("batch") < batch_id).agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    ranged = settle(batch.repartitionByRange(*order).withColumn("__b", F.spark_partition_id()), "ranged")
    rows = with_ordinal(ranged, F.col("__b"), *order)
    spark.createDataFrame([(ranged.count(),)], "n bigint").write.mode("overwrite").parquet(f"{path}/batch={batch_id}")
    return rows.withColumn("ordinal", F.col("ordinal") + F.lit(base))


def leader_stream(stream: DataFrame, plan: OverlapPlan, store_path: str, out_path: str, checkpoint: str, number_by: list[str] | None = None, keep: int | None = None):
    """Each micro-batch meets the stored keys, then its own rounds; a batch run again replaces its own rows.

    number_by: columns by which arrivals are numbered inside a batch, for streams without ordinals of their own.
    keep: how many batches back a stored leader still counts.
    """
    spark = stream.sparkSession

    def each(batch: DataFrame, batch_id: int) -> None:
        store = KeyStore(spark, store_path, plan, keep=keep)
        rows = batch if number_by is None else _numbered(batch, f"{store_path}/offsets", batch_id, number_by)
        rows = settle(rows.select("ordinal", "item_id", "size", "sig"), "batch")
        if not rows.isEmpty():
            leader_step(rows, plan, store, batch_id).write.mode("overwrite").parquet(f"{out_path}/batch={batch_id}")

    return stream.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def late_rows(query) -> int:
    """Rows that a finished or running query has dropped as later than its watermark, over all its progress reports."""
    return sum(op["numRowsDroppedByWatermark"] for p in query.recentProgress for op in p["stateOperators"])


def q_stream_leader(spark: SparkSession, sf_dir: str) -> DataFrame:
    """User-days as a stream of files in arrival order; the result equals the batch run's."""
    base = scratch(spark, "stream")
    sigs = settle(sig_userday(spark, sf_dir), "sig")
    third = (sigs.count() + 2) // 3
    for k in range(3):
        sigs.filter((F.col("ordinal") > k * third) & (F.col("ordinal") <= (k + 1) * third)).coalesce(1).write.mode("append").parquet(f"{base}/in")
    plan = OverlapPlan.build(SimilarityRule.jaccard("3/5"), range(2, 11))
    leader_stream(stream_signatures(spark, f"{base}/in"), plan, f"{base}/store", f"{base}/out", f"{base}/ckpt").awaitTermination()
    out = spark.read.schema("cluster_id bigint, ordinal bigint, elements array<string>").parquet(f"{base}/out/batch=*")
    return out.select("cluster_id", "ordinal", F.array_join("elements", "-").alias("elements"))


class _Writers(StatefulProcessor):
    """Per key: ordinals that have written it; readers learn all earlier ones that haven't expired."""

    def __init__(self, live_ms: int | None = None):
        self.live_ms = live_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.seen = handle.getListState("seen", "ordinal bigint", ttlDurationMs=self.live_ms)

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timer_values) -> Iterator[pd.DataFrame]:
        got = pd.concat(list(rows)).sort_values(["ordinal", "marks"])
        before = [r[0] for r in self.seen.get()]
        pairs, new = [], []
        for r in got.itertuples(index=False):
            if r.marks:
                new.append(r.ordinal)
            else:
                pairs += [(o, r.ordinal) for o in (*before, *new) if o < r.ordinal]
        if new:
            self.seen.appendList([(o,) for o in new])
        if pairs:
            yield pd.DataFrame(pairs, columns=["earlier", "later"])

    def close(self) -> None:
        pass


def pairs_stream(stream: DataFrame, plan: OverlapPlan, live_ms: int | None = None) -> DataFrame:
    """Similar pairs as items arrive; a pair may come from several keys, so dedupe downstream.

    live_ms: how long a marker counts after it was written, by the processing clock; the state store drops it then.
    """
    marks = mark_keys(stream, plan).select("key", "ordinal", F.lit(True).alias("marks"))
    probes = probe_keys(stream, plan).select("key", "ordinal", F.lit(False).alias("marks"))
    return marks.union(probes).groupBy("key").transformWithStateInPandas(_Writers(live_ms), "earlier bigint, later bigint", "append", "none" if live_ms is None else "processingTime")


def stream_events(spark: SparkSession, path: str) -> DataFrame:
    schema = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"
    return spark.readStream.schema(schema).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def behaviour_stream(events: DataFrame, kind: str = "tumbling", size: str = "1 day", slide: str = "6 hours", gap: str = "2 hours", late: str = "1 hour") -> DataFrame:
    """(window, user_id, sig) of event elements; rows later than the watermark go."""
    bucket = F.expr("cast(get_json_object(props, '$.k') as int) div 20")
    element = F.concat_ws(":", "event_type", bucket.cast("string"))
    span = {"tumbling": lambda: F.window("ts", size), "sliding": lambda: F.window("ts", size, slide), "session": lambda: F.session_window("ts", gap)}[kind]()
    return events.withWatermark("ts", late).groupBy(span.alias("span"), "user_id").agg(F.array_sort(F.collect_set(element)).alias("sig"))


def dedupe_stream(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def pairs_stream_join(left: DataFrame, right: DataFrame, plan: OverlapPlan, within: str = "3 days") -> DataFrame:
    """Probe-mark join of two timed streams (.., ts): bounded by watermarks on both sides."""
    a = left.withWatermark("ts", "1 hour")
    b = right.withWatermark("ts", "1 hour")
    table = F.broadcast(plan.to_df(left.sparkSession, "mark").select("size", "plan"))  # bounded by PLAN_LIMIT
    probe = F.broadcast(plan.to_df(left.sparkSession, "probe").select("size", "plan"))

    def keyed(df: DataFrame, t: DataFrame, name: str) -> DataFrame:
        rows = df.join(t, "size").select("ts", "ordinal", "sig", F.explode("plan").alias("p"))
        key = F.concat_ws("\u001f", F.col("p.tag").cast("string"), F.array_join(F.transform("p.pos", lambda i: F.element_at(F.col("sig"), i)), "\u001f"))
        return rows.select(F.col("ts").alias(f"{name}_ts"), F.col("ordinal").alias(name), key.alias(f"{name}_key"))

    x, y = keyed(a, table, "earlier"), keyed(b, probe, "later")
    return x.join(y, F.expr(f"earlier_key = later_key AND earlier_ts <= later_ts AND earlier_ts >= later_ts - INTERVAL {within}")).select("earlier", "later")


__all__ = ["leader_stream", "late_rows", "pairs_stream", "pairs_stream_join", "behaviour_stream", "dedupe_stream", "stream_events", "stream_signatures", "q_stream_leader"]
