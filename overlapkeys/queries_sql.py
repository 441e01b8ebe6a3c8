"""The relational surface around the methods: joins, aggregates, windows, sets, functions over signature tables.

Most are one SQL text that both engines run, with ``{sig}`` as the signature table.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from overlapkeys import oracle_sql as O
from overlapkeys.functions import sql_functions
from overlapkeys.operators import leader as L
from overlapkeys.operators import retrieve as R
from overlapkeys.session import settle
from overlapkeys.sources.signatures import load

# name: (workload, Spark SQL, DuckDB SQL or None where the text is the same)
BOTH: dict[str, tuple[str, str, str | None]] = {
    "q_filter_contains": ("userday", "SELECT ordinal FROM {sig} WHERE array_contains(sig, 'click:0')", "SELECT ordinal FROM sig WHERE list_contains(sig, 'click:0')"),
    "q_filter_any": ("userday", "SELECT ordinal FROM {sig} WHERE arrays_overlap(sig, array('click:0', 'view:1'))", "SELECT ordinal FROM sig WHERE list_has_any(sig, ['click:0', 'view:1'])"),
    "q_filter_subset": ("part", "SELECT ordinal FROM {sig} WHERE size(array_except(array('sz1', 'sz2'), sig)) = 1", "SELECT ordinal FROM sig WHERE list_contains(sig, 'sz1') <> list_contains(sig, 'sz2')"),
    "q_filter_nullsafe": ("part", "SELECT ordinal FROM {sig} WHERE nullif(size, 5) <=> null", "SELECT ordinal FROM sig WHERE nullif(size, 5) IS NOT DISTINCT FROM NULL"),
    "q_filter_text": ("part", "SELECT ordinal FROM {sig} WHERE sig[0] LIKE 'Brand#1%' AND sig[0] RLIKE '[0-9]{{2}}$' AND ordinal BETWEEN 10 AND 900 AND size IN (5, 6)", "SELECT ordinal FROM sig WHERE sig[1] LIKE 'Brand#1%' AND regexp_matches(sig[1], '[0-9]{2}$') AND ordinal BETWEEN 10 AND 900 AND size IN (5, 6)"),
    "q_case_bucket": ("orders", "SELECT CASE WHEN size < 4 THEN 'small' WHEN size < 8 THEN 'middle' ELSE 'large' END AS bucket, count(*) AS n FROM {sig} GROUP BY 1", None),
    "q_filter_exists": ("customer", "SELECT ordinal FROM {sig} a WHERE EXISTS (SELECT 1 FROM {sig} b WHERE b.sig = a.sig AND b.ordinal < a.ordinal)", None),
    "q_filter_in": ("customer", "SELECT ordinal FROM {sig} WHERE sig IN (SELECT sig FROM {sig} GROUP BY sig HAVING count(*) > 3)", None),
    "q_filter_scalar": ("orders", "SELECT ordinal FROM {sig} WHERE size > (SELECT avg(size) FROM {sig})", None),
    "q_agg_sizes": ("orders", "SELECT CAST(size AS bigint) AS size, count(*) AS n FROM {sig} GROUP BY size", None),
    "q_agg_distinct": ("userday", "SELECT count(DISTINCT e) AS elements, count(*) AS total FROM (SELECT explode(sig) AS e FROM {sig})", "SELECT count(DISTINCT e) AS elements, count(*) AS total FROM (SELECT unnest(sig) AS e FROM sig)"),
    "q_agg_grouping_sets": ("userday", "SELECT CAST(size AS bigint) AS size, CAST(ordinal % 3 AS bigint) AS g, count(*) AS n FROM {sig} GROUP BY GROUPING SETS ((size), (ordinal % 3), ())", "SELECT size::BIGINT AS size, g, count(*) AS n FROM (SELECT size, ordinal % 3 AS g FROM sig) GROUP BY GROUPING SETS ((size), (g), ())"),
    "q_agg_cube": ("userday", "SELECT CAST(size AS bigint) AS size, g, count(*) AS n FROM (SELECT size, ordinal % 3 AS g FROM {sig}) GROUP BY CUBE (size, g)", None),
    "q_agg_rollup": ("userday", "SELECT CAST(size AS bigint) AS size, g, count(*) AS n FROM (SELECT size, ordinal % 3 AS g FROM {sig}) GROUP BY ROLLUP (size, g)", None),
    "q_agg_collect": ("supplier", "SELECT sig[0] AS e, array_join(transform(array_sort(collect_list(ordinal)), x -> cast(x AS string)), ',') AS ids FROM {sig} GROUP BY 1", "SELECT sig[1] AS e, array_to_string(list_sort(list(ordinal)), ',') AS ids FROM sig GROUP BY 1"),
    "q_agg_minby": ("orders", "SELECT CAST(size AS bigint) AS size, min_by(item_id, ordinal) AS first_item, max_by(item_id, ordinal) AS last_item FROM {sig} GROUP BY size", "SELECT size::BIGINT AS size, arg_min(item_id, ordinal) AS first_item, arg_max(item_id, ordinal) AS last_item FROM sig GROUP BY size"),
    "q_agg_filter": ("orders", "SELECT count(*) FILTER (WHERE size > 4) AS large, count(*) FILTER (WHERE size <= 4) AS small FROM {sig}", None),
    "q_agg_percentile": ("orders", "SELECT CAST(percentile(size, 0.5) AS double) AS med, CAST(percentile(size, 0.9) AS double) AS p90 FROM {sig}", "SELECT quantile_cont(size, 0.5)::DOUBLE AS med, quantile_cont(size, 0.9)::DOUBLE AS p90 FROM sig"),
    "q_agg_moments": ("orders", "SELECT round(avg(size), 6) AS mean, round(stddev_samp(size), 6) AS sd, round(regr_slope(CAST(size AS double), CAST(item_id AS double)), 9) AS slope FROM {sig}", "SELECT round(avg(size), 6) AS mean, round(stddev_samp(size), 6) AS sd, round(regr_slope(size::DOUBLE, item_id::DOUBLE), 9) AS slope FROM sig"),
    "q_win_rank": ("customer", "SELECT ordinal, CAST(rank() OVER (PARTITION BY sig[0] ORDER BY sig[1]) AS bigint) AS r FROM {sig}", "SELECT ordinal, rank() OVER (PARTITION BY sig[1] ORDER BY sig[2]) AS r FROM sig"),
    "q_win_denserank": ("customer", "SELECT ordinal, CAST(dense_rank() OVER (PARTITION BY sig[0] ORDER BY sig[1]) AS bigint) AS r FROM {sig}", "SELECT ordinal, dense_rank() OVER (PARTITION BY sig[1] ORDER BY sig[2]) AS r FROM sig"),
    "q_win_ntile": ("customer", "SELECT ordinal, CAST(ntile(4) OVER (PARTITION BY sig[0] ORDER BY ordinal) AS bigint) AS r FROM {sig}", "SELECT ordinal, ntile(4) OVER (PARTITION BY sig[1] ORDER BY ordinal) AS r FROM sig"),
    "q_win_cumedist": ("supplier", "SELECT ordinal, round(cume_dist() OVER (PARTITION BY sig[0] ORDER BY ordinal), 6) AS c, round(percent_rank() OVER (PARTITION BY sig[0] ORDER BY ordinal), 6) AS p FROM {sig}", "SELECT ordinal, round(cume_dist() OVER (PARTITION BY sig[1] ORDER BY ordinal), 6) AS c, round(percent_rank() OVER (PARTITION BY sig[1] ORDER BY ordinal), 6) AS p FROM sig"),
    "q_win_lag": ("userday", "SELECT ordinal, lag(ordinal) OVER w AS before, lead(ordinal) OVER w AS after FROM {sig} WINDOW w AS (PARTITION BY item_id ORDER BY ordinal)", None),
    "q_win_first_marker": ("userday", "SELECT ordinal, first_value(ordinal) OVER w AS f, nth_value(ordinal, 2) OVER w AS s FROM {sig} WINDOW w AS (PARTITION BY item_id ORDER BY ordinal ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)", None),
    "q_win_last_marker": ("userday", "SELECT ordinal, last_value(ordinal) OVER (PARTITION BY sig[0] ORDER BY ordinal ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS writer FROM {sig}", "SELECT ordinal, last_value(ordinal) OVER (PARTITION BY sig[1] ORDER BY ordinal ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS writer FROM sig"),
    "q_win_running_founders": ("customer", "SELECT ordinal, CAST(sum(f) OVER (PARTITION BY e ORDER BY ordinal) AS bigint) AS founders FROM (SELECT ordinal, sig[0] AS e, CASE WHEN min(ordinal) OVER (PARTITION BY sig) = ordinal THEN 1 ELSE 0 END AS f FROM {sig})", "SELECT ordinal, sum(f) OVER (PARTITION BY e ORDER BY ordinal)::BIGINT AS founders FROM (SELECT ordinal, sig[1] AS e, CASE WHEN min(ordinal) OVER (PARTITION BY sig) = ordinal THEN 1 ELSE 0 END AS f FROM sig)"),
    "q_win_sliding": ("userday", "SELECT ordinal, CAST(sum(size) OVER (PARTITION BY item_id ORDER BY ordinal ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS bigint) AS s FROM {sig}", None),
    "q_win_range_days": ("userday", "SELECT ordinal, count(*) OVER (PARTITION BY item_id ORDER BY ordinal RANGE BETWEEN 300 PRECEDING AND CURRENT ROW) AS n FROM {sig}", None),
    "q_win_ordinal": ("orders", "SELECT item_id, ordinal FROM {sig}", "SELECT item_id, row_number() OVER (ORDER BY item_id) AS ordinal FROM sig"),
    "q_sort_offset": ("orders", "SELECT ordinal, item_id FROM {sig} ORDER BY size DESC, ordinal LIMIT 20 OFFSET 30", None),
    "q_set_union": ("customer", "SELECT sig[0] AS e FROM {sig} UNION SELECT sig[1] FROM {sig}", "SELECT sig[1] AS e FROM sig UNION SELECT sig[2] FROM sig"),
    "q_set_intersect": ("customer", "SELECT sig[0] AS e FROM {sig} WHERE ordinal < 200 INTERSECT SELECT sig[0] FROM {sig} WHERE ordinal > 900", "SELECT sig[1] AS e FROM sig WHERE ordinal < 200 INTERSECT SELECT sig[1] FROM sig WHERE ordinal > 900"),
    "q_set_except": ("customer", "SELECT sig FROM (SELECT array_join(sig, '-') AS sig, ordinal FROM {sig}) WHERE ordinal < 800 EXCEPT SELECT sig FROM (SELECT array_join(sig, '-') AS sig, ordinal FROM {sig}) WHERE ordinal >= 800", "SELECT sig FROM (SELECT array_to_string(sig, '-') AS sig, ordinal FROM sig) WHERE ordinal < 800 EXCEPT SELECT sig FROM (SELECT array_to_string(sig, '-') AS sig, ordinal FROM sig) WHERE ordinal >= 800"),
    "q_set_exceptall": ("customer", "SELECT sig[0] AS e FROM {sig} EXCEPT ALL SELECT sig[0] FROM {sig} WHERE ordinal % 2 = 0", "SELECT sig[1] AS e FROM sig EXCEPT ALL SELECT sig[1] FROM sig WHERE ordinal % 2 = 0"),
    "q_set_intersectall": ("customer", "SELECT sig[0] AS e FROM {sig} WHERE ordinal % 2 = 0 INTERSECT ALL SELECT sig[0] FROM {sig} WHERE ordinal % 3 = 0", "SELECT sig[1] AS e FROM sig WHERE ordinal % 2 = 0 INTERSECT ALL SELECT sig[1] FROM sig WHERE ordinal % 3 = 0"),
    "q_fn_string": ("customer", "SELECT ordinal, upper(concat_ws('_', sig)) AS u, lpad(substr(sig[0], 2), 4, '0') AS l, CAST(length(array_join(sig, '')) AS bigint) AS n, translate(sig[0], 'B', 'b') AS t, trim(concat(' ', sig[1], ' ')) AS m FROM {sig}", "SELECT ordinal, upper(array_to_string(sig, '_')) AS u, lpad(substr(sig[1], 2), 4, '0') AS l, length(array_to_string(sig, ''))::BIGINT AS n, translate(sig[1], 'B', 'b') AS t, trim(' ' || sig[2] || ' ') AS m FROM sig"),
    "q_fn_regexp": ("part", "SELECT ordinal, regexp_extract(sig[0], '([0-9]+)', 1) AS d, regexp_replace(sig[0], '[0-9]', 'x') AS r FROM {sig}", "SELECT ordinal, regexp_extract(sig[1], '([0-9]+)', 1) AS d, regexp_replace(sig[1], '[0-9]', 'x', 'g') AS r FROM sig"),
    "q_fn_math": ("orders", "SELECT ordinal, CAST(ceil(size / 2.0) AS bigint) AS c, CAST(ordinal % 7 AS bigint) AS m, round(sqrt(size), 6) AS q, round(log2(size), 6) AS g, CAST(greatest(size, 4) AS bigint) AS x FROM {sig}", None),
    "q_fn_bits": ("orders", "SELECT ordinal, CAST(shiftleft(1, size) - 1 AS bigint) AS bound, CAST(bit_count(ordinal) AS bigint) AS ones, ordinal & 7 AS low FROM {sig}", "SELECT ordinal, ((1 << size) - 1)::BIGINT AS bound, bit_count(ordinal)::BIGINT AS ones, ordinal & 7 AS low FROM sig"),
    "q_fn_array": ("userday", "SELECT ordinal, array_join(slice(sig, 1, 2), '-') AS head, element_at(sig, -1) AS last, CAST(size(array_union(sig, array('x'))) AS bigint) AS n, array_join(array_except(sig, array('click:0')), '-') AS r FROM {sig}", "SELECT ordinal, array_to_string(list_slice(sig, 1, 2), '-') AS head, sig[-1] AS last, (len(sig) + 1)::BIGINT AS n, array_to_string(list_filter(sig, lambda x: x <> 'click:0'), '-') AS r FROM sig"),
    "q_fn_explode": ("customer", "SELECT ordinal, CAST(p AS bigint) AS p, e FROM {sig} LATERAL VIEW posexplode(sig) t AS p, e", "SELECT ordinal, unnest(range(0, size))::BIGINT AS p, unnest(sig) AS e FROM sig"),
    "q_fn_higher_order": ("userday", "SELECT ordinal, array_join(transform(sig, x -> upper(x)), '-') AS u, CAST(size(filter(sig, x -> x LIKE 'c%')) AS bigint) AS c, exists(sig, x -> x = 'view:0') AS v, CAST(aggregate(sig, 0, (a, x) -> a + length(x)) AS bigint) AS n FROM {sig}", "SELECT ordinal, array_to_string(list_transform(sig, lambda x: upper(x)), '-') AS u, len(list_filter(sig, lambda x: x LIKE 'c%'))::BIGINT AS c, list_contains(sig, 'view:0') AS v, list_sum(list_transform(sig, lambda x: length(x)))::BIGINT AS n FROM sig"),
    "q_fn_map": ("customer", "SELECT ordinal, array_join(map_keys(m), '-') AS k, m['R1'] AS r FROM (SELECT ordinal, map_from_entries(transform(sig, x -> struct(x, length(x)))) AS m FROM {sig}) WHERE map_contains_key(m, 'R1')", "SELECT ordinal, array_to_string(sig, '-') AS k, 2 AS r FROM sig WHERE list_contains(sig, 'R1')"),
    "q_fn_struct": ("customer", "SELECT s.o AS ordinal, s.f AS f FROM (SELECT named_struct('o', ordinal, 'f', sig[0]) AS s FROM {sig})", "SELECT ordinal, sig[1] AS f FROM sig"),
}

# name: (table, Spark SQL, DuckDB SQL or None)
TABLE: dict[str, tuple[str, str, str | None]] = {
    "q_scan_prune": ("lineitem", "SELECT l_orderkey, l_quantity FROM {t} WHERE l_quantity > 45", "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity > 45"),
    "q_fn_date": ("events", "SELECT event_id, CAST(to_date(ts) AS string) AS day, CAST(hour(ts) AS bigint) AS h, CAST(datediff(to_date(ts), DATE '2024-01-01') AS bigint) AS n FROM {t}", "SELECT event_id, ts::DATE::VARCHAR AS day, hour(ts) AS h, date_diff('day', DATE '2024-01-01', ts::DATE) AS n FROM events"),
    "q_fn_json": ("events", "SELECT event_id, CAST(get_json_object(props, '$.k') AS bigint) AS k, CAST(from_json(props, 'k int').k AS bigint) AS k2 FROM {t}", "SELECT event_id, json_extract_string(props, '$.k')::BIGINT AS k, json_extract_string(props, '$.k')::BIGINT AS k2 FROM events"),
    "q_agg_pivot": ("events", "SELECT * FROM (SELECT user_id, event_type FROM {t}) PIVOT (count(*) FOR event_type IN ('click' AS click, 'view' AS view))", "SELECT user_id, nullif(count(*) FILTER (event_type = 'click'), 0) AS click, nullif(count(*) FILTER (event_type = 'view'), 0) AS view FROM events GROUP BY 1"),
}


def register(add, sigs_of, plan_of) -> None:
    for name, (w, spark_sql, duck) in BOTH.items():
        add(name, lambda s, d, w=w, q=spark_sql: s.sql(q, sig=sigs_of(s, d, w)), O.query(w, [], duck if duck is not None else spark_sql.replace("{sig}", "sig")))
    for name, (t, spark_sql, duck) in TABLE.items():
        add(name, lambda s, d, t=t, q=spark_sql: s.sql(q, t=load(s, d, t)), duck)

    def on(name, w, f, ctes, body):
        add(name, lambda s, d: f(sigs_of(s, d, w), plan_of(w)), None if body is None else O.query(w, ctes, body))

    lead = [O.pairs(), O.LEADER]
    on("q_filter_theta", "userday", lambda s, p: R.simple_verified(s, p).select("earlier", "later"), [O.pairs()], "SELECT earlier, later FROM pairs")
    on("q_join_plan_broadcast", "part", lambda s, p: s.join(F.broadcast(p.counts_df(s.sparkSession)), "size").select("ordinal", "mark_keys"), [], "SELECT ordinal, 5::BIGINT AS mark_keys FROM sig")  # one row a size
    on("q_join_size_band", "userday", lambda s, p: s.select("ordinal", F.explode(F.sequence(F.ceil(F.col("size") * 0.6 - 1e-9).cast("int"), F.floor(F.col("size") / 0.6 + 1e-9).cast("int"))).alias("y")).groupBy("y").agg(F.count("*").alias("n")).join(s.groupBy(F.col("size").alias("y")).agg(F.count("*").alias("m")), "y").select(F.col("y").cast("bigint").alias("size"), (F.col("n") * F.col("m")).alias("pairs")), [], "SELECT b.size::BIGINT AS size, count(*) AS pairs FROM sig a JOIN sig b ON a.size BETWEEN ceil(b.size * 0.6 - 1e-9) AND floor(b.size / 0.6 + 1e-9) GROUP BY 1")
    on("q_join_full", "part", lambda s, p: settle(L.leader(s, p), "a").select("ordinal", "cluster_id").filter("ordinal <= 1500").join(s.select("ordinal", F.col("item_id").alias("item")).filter("ordinal > 500"), "ordinal", "full"), lead, "SELECT ordinal, cluster_id, item FROM (SELECT * FROM clusters WHERE ordinal <= 1500) FULL JOIN (SELECT ordinal, item_id AS item FROM sig WHERE ordinal > 500) USING (ordinal)")
    on("q_asof_marker", "userday", lambda s, p: s.withColumn("marker", F.last(F.when(F.col("size") >= 4, F.col("ordinal")), ignorenulls=True).over(W.partitionBy("item_id").orderBy("ordinal").rowsBetween(W.unboundedPreceding, -1))).select("ordinal", "marker"), [], "SELECT a.ordinal, max(b.ordinal) AS marker FROM sig a LEFT JOIN sig b ON a.item_id = b.item_id AND b.ordinal < a.ordinal AND b.size >= 4 GROUP BY 1")
    add(
        "q_join_interval",
        lambda s, d: s.sql("SELECT b.event_id AS bought, c.event_id AS clicked FROM {t} b JOIN {t} c ON b.user_id = c.user_id AND c.ts < b.ts AND c.ts >= b.ts - INTERVAL 3 DAYS WHERE b.event_type = 'purchase' AND c.event_type = 'click'", t=load(s, d, "events")),
        "SELECT b.event_id AS bought, c.event_id AS clicked FROM events b JOIN events c ON b.user_id = c.user_id AND c.ts < b.ts AND c.ts >= b.ts - INTERVAL 3 DAY WHERE b.event_type = 'purchase' AND c.event_type = 'click'",
    )
    topk = "SELECT a.ordinal, p.earlier FROM sig a, LATERAL (SELECT earlier FROM pairs WHERE later = a.ordinal ORDER BY overlap DESC, earlier LIMIT 2) p"

    def lateral(s: DataFrame, p) -> DataFrame:
        pairs = R.similar_pairs(s, p).select("earlier", "later", "overlap")
        best = pairs.withColumn("r", F.row_number().over(W.partitionBy("later").orderBy(F.desc("overlap"), "earlier")))
        return best.filter("r <= 2").select(F.col("later").alias("ordinal"), "earlier")

    on("q_topk_neighbours", "part", lateral, [O.pairs()], topk)
    on(
        "q_join_lateral", "part",
        lambda s, p: s.sparkSession.sql("SELECT a.ordinal, t.earlier FROM {s} a, LATERAL (SELECT p.earlier FROM {p} p WHERE p.later = a.ordinal ORDER BY p.overlap DESC, p.earlier LIMIT 2) t", s=s, p=settle(R.similar_pairs(s, p), "pairs")),
        [O.pairs()], topk,
    )
    on("q_sort_assignments", "part", lambda s, p: L.leader(s, p).select("cluster_id", "ordinal").orderBy("cluster_id", "ordinal"), lead, "SELECT cluster_id, ordinal FROM clusters")
    on("q_agg_approx", "userday", lambda s, p: s.select(F.explode("sig").alias("e")).agg(F.approx_count_distinct("e").alias("n")), [], None)
    on("q_sql_functions", "part", lambda s, p: sql_functions.similar_by_sql(s), [O.pairs()], "SELECT earlier, later, round(overlap::DOUBLE / (x + y - overlap), 6) AS score FROM pairs")
    from overlapkeys.queries import ALL_SUBS

    on(
        "q_udtf_keys", "supplier", lambda s, p: sql_functions.keys_by_udtf(s, p).select("ordinal", F.col("tag").cast("bigint").alias("tag"), F.regexp_replace("key", "\u001f", "-").alias("key")),
        ALL_SUBS, "SELECT ordinal, size::BIGINT AS tag, size || '-' || array_to_string(k, '-') AS key FROM keyed WHERE j = 3",
    )
    on("q_udaf_cluster_signature", "part", lambda s, p: sql_functions.cluster_signatures(L.leader(s, p)), [*lead, "e AS (SELECT cluster_id, unnest(sig) AS e FROM clusters JOIN sig USING (ordinal))", "c AS (SELECT cluster_id, e, row_number() OVER (PARTITION BY cluster_id ORDER BY count(*) DESC, e) AS r FROM e GROUP BY 1, 2)"], "SELECT cluster_id, array_to_string(list_sort(list(e)), '-') AS sig FROM c WHERE r <= 5 GROUP BY 1")
    on(
        "q_keys_arrow", "userday", lambda s, p: sql_functions.keys_by_arrow(s, p).groupBy("ordinal").agg(F.count("*").alias("keys")),
        ALL_SUBS, "SELECT ordinal, count(*) AS keys FROM keyed JOIN need ON need.x = size AND need = j GROUP BY 1",
    )

    def streamed(s, d):
        from overlapkeys.streaming import streams

        return streams.q_stream_leader(s, d)

    add("q_stream_leader", streamed, O.query("userday", lead, "SELECT cluster_id, ordinal, array_to_string(sig, '-') AS elements FROM clusters JOIN sig USING (ordinal)"))
