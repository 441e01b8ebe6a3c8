"""SQL surface: SQL-defined functions, a UDTF for keys, a grouped aggregate, an Arrow key generator."""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf

from overlapkeys.plans.overlap_plan import OverlapPlan
from overlapkeys.plans.rules import SimilarityRule


def register(spark: SparkSession) -> None:
    """sig_canonical, sig_jaccard, sig_similar: expanded by the analyzer, no Python."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sig_canonical(s ARRAY<STRING>) RETURNS ARRAY<STRING> RETURN array_sort(array_distinct(array_compact(s)))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sig_jaccard(a ARRAY<STRING>, b ARRAY<STRING>) RETURNS DOUBLE RETURN size(array_intersect(a, b)) / (size(a) + size(b) - size(array_intersect(a, b)))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sig_similar(a ARRAY<STRING>, b ARRAY<STRING>, num INT, den INT) RETURNS BOOLEAN RETURN size(array_intersect(a, b)) * (den + num) >= num * (size(a) + size(b))")


def similar_by_sql(sigs: DataFrame) -> DataFrame:
    """Similar pairs by SQL alone: an equi-join on elements, a pair counts at its first common one."""
    spark = sigs.sparkSession
    register(spark)
    text = """
        WITH flat AS (SELECT ordinal, sig_canonical(sig) AS sig, explode(sig) AS e FROM {s})
        SELECT a.ordinal AS earlier, b.ordinal AS later, round(sig_jaccard(a.sig, b.sig), 6) AS score
        FROM flat a JOIN flat b ON a.e = b.e AND a.ordinal < b.ordinal
        WHERE element_at(array_intersect(a.sig, b.sig), 1) = a.e AND sig_similar(a.sig, b.sig, 3, 5)
    """
    return spark.sql(text, s=sigs)


class SubSignatureKeys:
    def eval(self, sig: list, theta: str, sizes: list, role: str):
        plan = OverlapPlan.build(SimilarityRule.jaccard(theta), sizes)
        for tag, pos in plan.combos(len(sig), role):
            yield tag, "\x1f".join([str(tag), *(sig[p - 1] for p in pos)])


def keys_by_udtf(sigs: DataFrame, plan: OverlapPlan) -> DataFrame:
    spark = sigs.sparkSession
    spark.udtf.register("sub_signature_keys", udtf(SubSignatureKeys, returnType="tag int, key string"))
    sizes = ", ".join(map(str, plan.sizes))
    return spark.sql(f"SELECT s.ordinal, k.tag, k.key FROM {{s}} s, LATERAL sub_signature_keys(s.sig, '{plan.rule.num}/{plan.rule.den}', array({sizes}), 'mark') k", s=sigs)


def _frequent(elements: pd.Series) -> str:
    n = elements.explode().value_counts()
    return "-".join(sorted(sorted(n.index, key=lambda e: (-n[e], e))[:5]))


def cluster_signatures(assigned: DataFrame) -> DataFrame:
    """(cluster_id, sig): the five most frequent elements, by a grouped aggregate in Python."""
    return assigned.groupBy("cluster_id").agg(pandas_udf(_frequent, "string")("elements").alias("sig"))


def keys_by_arrow(sigs: DataFrame, plan: OverlapPlan, role: str = "probe") -> DataFrame:
    """Keys without a plan table, for plans too large to broadcast."""
    need = {x: plan.partner_sizes(x) for x in plan.sizes}
    least = {(x, y): plan.need(x, y) for x in plan.sizes for y in need[x]}
    mark = {x: plan.overlap_sizes(x) for x in plan.sizes}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out: tuple[list, list, list] = ([], [], [])
            for ordinal, sig in zip(b.column("ordinal").to_pylist(), b.column("sig").to_pylist()):
                x = len(sig)
                wanted = [(y, least[x, y]) for y in need[x]] if role == "probe" else [(x, j) for j in mark[x]]
                for tag, j in wanted:
                    for c in combinations(sig, j):
                        out[0].append(ordinal)
                        out[1].append(tag)
                        out[2].append("\x1f".join([str(tag), *c]))
            yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.int64()), pa.array(out[1], pa.int32()), pa.array(out[2], pa.string())], names=["ordinal", "tag", "key"])

    return sigs.select("ordinal", "sig").mapInArrow(run, "ordinal bigint, tag int, key string")
