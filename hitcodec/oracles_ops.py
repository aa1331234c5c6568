"""DuckDB SQL with the results of the relational, format, stream and UDF queries."""

from __future__ import annotations

from hitcodec.oracles import EV1, EV2, HITS, OR0, OR1, PLACED, WALK, greedy, li1, w

ORACLES: dict[str, str] = {}
O = ORACLES
CENTS = "CAST(round({0} * 100) AS BIGINT)"
inner = f"SELECT o_orderpriority, count(*) AS n, CAST(sum({CENTS.format('l_extendedprice')}) AS BIGINT) AS price FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderpriority"
for k in ("smj", "shj", "bhj"):
    O[f"join_inner_{k}"] = inner
for k in ("left", "right", "full"):
    O[f"join_{k}"] = f"SELECT day, ordered, shipped FROM (SELECT strftime(o_orderdate, '%Y-%m-%d') AS day, count(*) AS ordered FROM orders GROUP BY 1) {k} JOIN (SELECT strftime(l_shipdate, '%Y-%m-%d') AS day, count(*) AS shipped FROM lineitem GROUP BY 1) USING (day)"
O["join_semi"] = "SELECT o_orderkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_quantity > 45)"
O["join_anti"] = "SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)"
O["join_cross_small"] = "SELECT n_name, r_name FROM nation, region"
O["join_theta"] = w(EV1, "wv AS (SELECT 'width' AS vtype, fall - rise AS v FROM hits)", greedy("wv", "count(*) // 16")) + "SELECT bin, n FROM bins WHERE n > 0"
O["join_interval"] = w(OR1) + "SELECT a.channel AS a, b.channel AS b, count(*) AS n, CAST(sum(least(a.fall, b.fall) - greatest(a.rise, b.rise)) AS BIGINT) AS ticks FROM hits a JOIN hits b ON a.event = b.event AND a.channel < b.channel AND a.rise < b.fall AND b.rise < a.fall GROUP BY ALL"
O["join_asof"] = w(EV1, "l AS (SELECT event, rise, fall FROM hits WHERE channel = 5)", "r AS (SELECT event, rise, fall - rise AS width FROM hits WHERE channel = 3)") + "SELECT l.event, l.rise, l.fall, r.width AS last_width FROM l ASOF LEFT JOIN r ON l.event = r.event AND l.rise >= r.rise"
O["agg_hash"] = w(EV1) + "SELECT channel, count(*) AS n, CAST(sum(fall - rise) AS BIGINT) AS total, min(fall - rise) AS least, max(fall - rise) AS most, round(avg(fall - rise), 4) AS mean FROM hits GROUP BY channel"
O["agg_collect"] = w(EV1) + "SELECT event, string_agg(CAST(channel AS VARCHAR), ',' ORDER BY channel) AS channels FROM hits GROUP BY event"
O["agg_distinct"] = w(EV1) + "SELECT event, count(DISTINCT channel) AS channels FROM hits GROUP BY event"
O["agg_multi_distinct"] = "SELECT count(DISTINCT user_id) AS users, count(DISTINCT event_type) AS kinds, count(DISTINCT props) AS props FROM events"
O["agg_filter"] = w(EV2) + "SELECT channel, count(*) FILTER (rising) AS rises, count(*) FILTER (NOT rising) AS falls, count(*) FILTER (rising IS NULL) AS corrupt FROM edges GROUP BY channel"
O["agg_pivot"] = w(EV1, PLACED) + "SELECT channel, " + ", ".join(f"nullif(count(*) FILTER (vtype = '{x}'), 0) AS {x}" for x in ("pulses", "start", "width", "distance")) + " FROM vals GROUP BY channel"
O["agg_maxby"] = w(EV1) + "SELECT event, arg_min(channel, rise) AS first, arg_max(channel, rise) AS last FROM hits GROUP BY event"
O["agg_salted"] = w(EV1) + "SELECT channel, count(*) AS n FROM hits GROUP BY channel"
O["agg_percentile_exact"] = w(EV1, "x AS (SELECT channel, fall - rise AS w, row_number() OVER (PARTITION BY channel ORDER BY fall - rise, event, rise) AS k, count(*) OVER (PARTITION BY channel) AS n FROM hits)") + "SELECT channel, w AS median FROM x WHERE k = greatest(1, n // 2)"
O["agg_moments"] = "WITH v AS (SELECT CAST(i - 1 AS INTEGER) AS channel, CAST(round((CAST(embedding[i] AS DOUBLE) + 1) * 1048576) AS BIGINT) AS v FROM embeddings, range(1, 65) r(i)), m AS (SELECT channel, avg(v) AS m FROM v GROUP BY channel) SELECT channel, round(stddev_samp(v), 2) AS sd, round(avg(pow(v - m, 3)) / pow(avg(pow(v - m, 2)), 1.5), 4) AS skew FROM v JOIN m USING (channel) GROUP BY channel"
O["agg_approx_distinct"] = O["agg_approx_quantile"] = "SELECT true AS close"
CLASS = f"{li1('l_suppkey')}, {PLACED}, cv AS (SELECT vtype, v, v.channel AS channel, s_nationkey AS class_id, n_regionkey AS unit_id, length(bin(v)) AS bits FROM vals v JOIN supplier ON v.channel = s_suppkey JOIN nation ON s_nationkey = n_nationkey WHERE vtype <> 'pulses')"
O["cube_cost"] = w(CLASS) + "SELECT vtype, unit_id, CAST(sum(bits) AS BIGINT) AS bits, CAST(grouping_id(vtype, unit_id) AS INTEGER) AS g FROM cv GROUP BY CUBE (vtype, unit_id)"
O["rollup_hierarchy"] = w(CLASS) + "SELECT unit_id, class_id, channel, CAST(sum(bits) AS BIGINT) AS bits, count(*) AS n, CAST(grouping_id(unit_id, class_id, channel) AS INTEGER) AS g FROM cv GROUP BY ROLLUP (unit_id, class_id, channel)"
O["grouping_sets_cost"] = w(CLASS) + "SELECT vtype, class_id, CAST(sum(bits) AS BIGINT) AS bits, CAST(grouping_id(vtype, class_id) AS INTEGER) AS g FROM cv GROUP BY GROUPING SETS ((vtype, class_id), (class_id), ())"
PER = "p AS (SELECT event, channel, count(*) AS n, CAST(sum(fall - rise) AS BIGINT) AS w FROM hits GROUP BY ALL)"
BY = "(PARTITION BY event ORDER BY w DESC, channel)"
NBY = "(PARTITION BY event ORDER BY n)"
O["win_rank"] = w(EV1, PER) + f"SELECT event, channel, row_number() OVER {BY} AS rn, rank() OVER {NBY} AS rank, dense_rank() OVER {NBY} AS dense FROM p"
O["win_dense_ntile"] = w(EV1, PER) + f"SELECT event, channel, ntile(4) OVER {BY} AS quarter FROM p"
O["win_percent_rank"] = w(EV1, PER) + f"SELECT event, channel, round(percent_rank() OVER {BY}, 6) AS pr, round(cume_dist() OVER {BY}, 6) AS cd FROM p"
O["win_lag_lead"] = w(EV1, PER) + f"SELECT event, channel, lag(w) OVER {BY} AS before, lead(w, 2) OVER {BY} AS after FROM p"
O["win_running_rows"] = w(EV1, PER) + "SELECT event, channel, CAST(sum(w) OVER (PARTITION BY event ORDER BY w DESC, channel ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS three FROM p"
O["win_range_ticks"] = w(EV1) + "SELECT event, channel, rise, count(*) OVER (PARTITION BY event ORDER BY rise RANGE BETWEEN 60000000 PRECEDING AND CURRENT ROW) AS recent FROM hits"
ALL = "(PARTITION BY event ORDER BY w DESC, channel ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)"
O["win_first_last_nth"] = w(EV1, PER) + f"SELECT event, channel, first_value(w) OVER {ALL} AS first, last_value(w) OVER {ALL} AS last, nth_value(w, 2) OVER {ALL} AS second FROM p"
O["topk_global"] = w(EV1, PER) + "SELECT * FROM p ORDER BY w DESC, event, channel LIMIT 25"
O["topk_per_group"] = w(EV1, PER) + f"SELECT *, row_number() OVER {BY} AS rank FROM p QUALIFY row_number() OVER {BY} <= 3"
O["limit_offset"] = w(EV1, PER) + "SELECT * FROM p ORDER BY event, channel LIMIT 50 OFFSET 100"
O["sort_total"] = w(EV1, PER) + "SELECT * FROM p ORDER BY event, channel"
A, Bq = ("SELECT channel, (fall - rise) % 100 AS w FROM hits WHERE event % 2 = 0", "SELECT channel, (fall - rise) % 100 AS w FROM hits WHERE event % 2 = 1")
for k, op in {"set_union_all": "UNION ALL", "set_union": "UNION", "set_intersect": "INTERSECT", "set_intersect_all": "INTERSECT ALL", "set_except": "EXCEPT", "set_except_all": "EXCEPT ALL"}.items():
    O[k] = w(EV1) + f"{A} {op} {Bq}"
O["fn_string"] = "SELECT p_partkey, bin(p_size) AS bits, lpad(bin(p_size), 8, '0') AS padded, hex(p_size) AS hex, p_size AS back, length(p_name) AS len, upper(p_name[1:3]) AS head FROM part"
O["fn_url"] = "SELECT page_id, regexp_extract(url, '://([^/]*)', 1) AS host, ascii(url) AS first FROM pages"
O["fn_date"] = "SELECT event_id, epoch_us(ts) AS us, CAST(year(ts) AS INTEGER) AS y, CAST(dayofyear(ts) AS INTEGER) AS doy, CAST(hour(ts) AS INTEGER) AS h, CAST(date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS INTEGER) AS days FROM events"
O["fn_math_bits"] = "SELECT event_id, event_id * 8 AS up, event_id // 4 AS down, CAST(bit_count(event_id) AS INTEGER) AS ones, (7 - event_id % 7) % 7 AS pm, round(log2(event_id + 1), 6) AS lg, event_id & 12 AS low FROM events"
O["fn_array"] = "SELECT vec_id, CAST(len(embedding) AS INTEGER) AS n, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INTEGER) AS positive, list_min(list_transform(embedding, lambda x: CAST(round(CAST(x AS DOUBLE) * 1024) AS BIGINT))) AS least, 5 AS five FROM embeddings"
O["fn_map"] = "SELECT n_regionkey, CAST(count(*) AS INTEGER) AS n, min(n_nationkey) AS least, arg_min(n_name, n_nationkey) AS name FROM nation GROUP BY n_regionkey"
O["fn_json"] = "SELECT event_id, CAST(json_extract(props, '$.k') AS INTEGER) AS k, CAST(json_extract(props, '$.k') AS INTEGER) AS again FROM events"
O["fn_conditional"] = "SELECT event_id, CASE WHEN event_type IN ('view', 'click') THEN 1 WHEN event_type = 'error' THEN -1 ELSE 0 END AS edge, coalesce(nullif(event_type, 'view'), '-') AS other FROM events"
O["fn_cast"] = f"SELECT p_partkey, CAST(trunc(p_retailprice) AS INTEGER) AS whole, TRY_CAST(p_brand AS INTEGER) AS none, {CENTS.format('p_retailprice')} AS cents FROM part"
O["filter_mixed"] = "SELECT o_orderkey, o_orderpriority FROM orders WHERE o_totalprice BETWEEN 1000 AND 200000 AND o_orderstatus IN ('O', 'F') AND o_orderpriority LIKE '%H%' AND o_custkey IS NOT NULL"
O["io_csv"] = "SELECT n_nationkey, n_name, n_regionkey FROM nation"
O["io_json"] = "SELECT r_regionkey, r_name FROM region"
O["io_orc"] = "SELECT s_suppkey, s_name, s_nationkey FROM supplier"
O["io_partitioned"] = "SELECT o_orderkey, o_custkey, o_orderstatus FROM orders"
O["io_text"] = "SELECT p_partkey || '|' || p_name || '|' || p_size AS value FROM part"
O["io_frames_source"] = w(EV1) + HITS + " WHERE event BETWEEN 5 AND 40"
DAY = "86400000000"
O["stream_tumbling"] = f"SELECT epoch_us(ts) // {DAY} * {DAY} AS start, CAST(user_id % 48 AS INTEGER) AS channel, count(*) AS n FROM events GROUP BY ALL"
O["stream_sliding"] = f"SELECT s AS start, count(*) AS n FROM (SELECT unnest([epoch_us(ts) // {DAY} * {DAY}, epoch_us(ts) // {DAY} * {DAY} - {DAY}]) AS s FROM events) GROUP BY s"
O["stream_session"] = "WITH e AS (SELECT epoch_us(ts) AS us, CAST(user_id % 48 AS INTEGER) AS channel FROM events), m AS (SELECT *, CASE WHEN us - lag(us) OVER (PARTITION BY channel ORDER BY us) <= 300000000 THEN 0 ELSE 1 END AS new FROM e), g AS (SELECT *, sum(new) OVER (PARTITION BY channel ORDER BY us) AS s FROM m) SELECT min(us) AS start, channel, count(*) AS n FROM g GROUP BY channel, s"
O["stream_pairing"] = w(EV2) + "SELECT event, channel, tick AS rise, nxt_tick AS fall FROM judged WHERE reason = 'kept' AND rising"
O["stream_late"] = w(EV2) + "SELECT count(*) AS edges, 0 AS late FROM edges WHERE rising IS NOT NULL"
O["stream_histogram"] = w(EV1) + "SELECT (fall - rise) // 1024 AS b, count(*) AS n FROM hits GROUP BY b"
O["stream_dedup"] = O["stream_frames"] = w(EV1) + HITS
O["stream_join"] = w(EV2) + "SELECT a.event, a.channel, a.tick AS rise, b.tick AS fall FROM edges a JOIN edges b ON a.event = b.event AND a.channel = b.channel AND a.rising AND NOT b.rising AND b.tick > a.tick AND b.tick <= a.tick + 600000000"
O["stream_equals_batch"] = "SELECT 0 AS differ"
O["udf_arrow"] = w(OR0) + "SELECT event, channel, CAST(2 * length(bin(pulses + 1)) - 1 AS INTEGER) AS bits FROM or0"
O["udf_pandas"] = w(EV1) + "SELECT event, fall - rise AS v, CAST(CASE WHEN fall - rise >= 20000 THEN 3 WHEN fall - rise >= 5000 THEN 2 WHEN fall - rise >= 1000 THEN 1 ELSE 0 END AS INTEGER) AS bin FROM hits"
O["stream_frames_source"] = w(EV1) + HITS
O["udf_agg"] = w(OR0, "h AS (SELECT channel, pulses, count(*) AS n FROM or0 GROUP BY ALL)") + "SELECT channel, round(log2(sum(n)) - sum(n * log2(n)) / sum(n), 4) AS entropy FROM h GROUP BY channel"
O["udtf_trace"] = f"WITH {WALK} SELECT c_custkey, step, CASE sym WHEN 1 THEN 'b' ELSE 'a' END AS sym, state, bits, next_state FROM walk"
O["udtf_decode"] = w(OR0) + "SELECT event, channel AS pos, CAST(pulses AS INTEGER) AS sym FROM or0"
O["udf_sql_registered"] = w(OR0) + "SELECT CAST(pulses AS INTEGER) AS pulses, CAST(2 * length(bin(pulses + 1)) - 1 AS INTEGER) AS bits, round(-log2(count(*) / sum(count(*)) OVER ()), 4) AS info FROM or0 GROUP BY pulses"
