"""DuckDB SQL with the results of the queries of the registry. Each oracle computes from the given tables alone."""

from __future__ import annotations

from hitcodec.sources.views import PULSE_STEPS

MIX = "((({0}) % 1000003) * (({0}) % 1000003)) % 1000003"


def mix(e: str) -> str:
    s = MIX.format(e)
    return f"(((({s}) * ({s})) % 1000003) * (({e}) % 1000003)) % 1000003"


STEPS = " ".join(f"WHEN u < {step} THEN {k}" for k, step in enumerate(PULSE_STEPS))
OR0 = f"""or0 AS (
  SELECT event, channel, id, CASE {STEPS} ELSE 0 END AS pulses FROM (
    SELECT event, channel, id, {mix("id * 7919 + 104729")} AS u FROM (
      SELECT o_orderkey AS event, CAST(c.range AS INTEGER) AS channel, o_orderkey * 48 + c.range AS id FROM orders, range(48) c))
)"""
EV1 = """hits AS (
  SELECT event_id // 24 AS event, CAST(user_id % 48 AS INTEGER) AS channel, epoch_us(ts) - 1704067200000000 AS rise,
         epoch_us(ts) - 1704067200000000 + CAST(round(value * 100) AS BIGINT) AS fall FROM events
)"""


def li1(channel: str) -> str:
    return f"""hits AS (
  SELECT event, channel, rise, rise + w AS fall FROM (
    SELECT l_orderkey AS event, CAST({channel} AS INTEGER) AS channel,
           CAST(round(l_extendedprice * 100) AS BIGINT) % 1024000 + 1024000 * date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE)) AS rise,
           CAST(l_quantity * 100 AS BIGINT) + CAST(round(l_discount * 100) AS BIGINT) AS w FROM lineitem)
)"""


OR1 = f"""{OR0}, each AS (
  SELECT event, channel, id, j.range AS j, id * 16 + j.range AS k FROM or0, range(8) j WHERE j.range < pulses
), drawn AS (
  SELECT *, {mix("id * 611953 + 31")} AS a, {mix("k * 7877 + 19")} AS b,
         2000 + 30 * channel + ({mix("k * 7907 + 7")}) % 1000 + ({mix("k * 7901 + 11")}) % 1000 + ({mix("k * 7883 + 13")}) % 1000 + ({mix("k * 7879 + 17")}) % 1000 AS width
  FROM each
), timed AS (
  SELECT *, 500 + b * b * b // 100000000000 AS dist FROM drawn
), placed_or AS (
  SELECT event, channel, width,
         a * a * a // 10000000000 + coalesce(CAST(sum(width + dist) OVER (PARTITION BY id ORDER BY j ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS BIGINT), 0) AS rise
  FROM timed
), hits AS (
  SELECT event, channel, rise, rise + width AS fall FROM placed_or
)"""
VIEWS = {"EV1": EV1, "LI1": li1("l_suppkey % 48"), "OR1": OR1}
EV2 = """edges AS (
  SELECT event_id // 336 AS event, CAST(user_id % 48 AS INTEGER) AS channel, epoch_us(ts) - 1704067200000000 AS tick,
         CASE WHEN event_type IN ('view', 'click') THEN true WHEN event_type IN ('signup', 'purchase') THEN false END AS rising FROM events
), ordered AS (
  SELECT *, lead(rising) OVER w AS nxt, lead(tick) OVER w AS nxt_tick, lag(rising) OVER w AS prv, lag(tick) OVER w AS prv_tick
  FROM edges WINDOW w AS (PARTITION BY event, channel, rising IS NULL ORDER BY tick, rising DESC)
), judged AS (
  SELECT event, channel, tick, rising, nxt_tick,
         CASE WHEN rising IS NULL THEN 'corrupt' WHEN rising AND NOT coalesce(nxt, true) THEN 'kept' WHEN rising THEN 'no_fall'
              WHEN coalesce(prv, false) THEN 'kept' ELSE 'no_rise' END AS reason FROM ordered
)"""
PLACED = """placed AS (
  SELECT *, min(rise) OVER (PARTITION BY event) AS ref, row_number() OVER c - 1 AS pos, lag(fall) OVER c AS before,
         count(*) OVER (PARTITION BY event, channel) AS pulses
  FROM hits WINDOW c AS (PARTITION BY event, channel ORDER BY rise, fall)
), vals AS (
  SELECT event, channel, 0 AS pos, 'pulses' AS vtype, pulses AS v FROM placed WHERE pos = 0
  UNION ALL SELECT event, channel, 0, 'start', rise - ref FROM placed WHERE pos = 0
  UNION ALL SELECT event, channel, pos, 'width', fall - rise FROM placed
  UNION ALL SELECT event, channel, pos - 1, 'distance', rise - before FROM placed WHERE pos > 0
)"""
HIST = f"""{PLACED}, n_events AS (SELECT count(DISTINCT event) AS e FROM hits
), hist AS (
  SELECT vtype, v, count(*) AS n FROM vals GROUP BY ALL
  UNION ALL SELECT 'pulses', 0, (SELECT e FROM n_events) * 48 - count(*) FROM vals WHERE vtype = 'pulses'
)"""
TICKS_PER_EPOCH = 1024000
EDGES = f"""flat AS (
  SELECT event, channel, rise AS tick, true AS rising FROM hits UNION ALL SELECT event, channel, fall, false FROM hits
), stepped AS (
  SELECT *, CASE WHEN coalesce(lag(tick // {TICKS_PER_EPOCH}) OVER w <> tick // {TICKS_PER_EPOCH}, true) THEN 1 ELSE 0 END AS new
  FROM flat WINDOW w AS (PARTITION BY event ORDER BY tick, channel, rising)
)"""

ORACLES: dict[str, str] = {}
O = ORACLES


def w(*ctes: str) -> str:
    return "WITH RECURSIVE " + ", ".join(ctes) + " "


HITS = "SELECT event, channel, rise, fall FROM hits"
O["tick_split"] = w(VIEWS["LI1"]) + "SELECT event, channel, rise, CAST(((rise % 500) + 500) % 500 AS INTEGER) AS fine, CAST(((((rise - ((rise % 500) + 500) % 500) // 500) % 2048) + 2048) % 2048 AS INTEGER) AS coarse, CAST(floor(rise / 1024000.0) AS BIGINT) AS epoch FROM hits"
O["tick_join"] = w(EV1) + HITS
O["ref_min"] = w(EV1) + "SELECT event, channel, min(rise) OVER (PARTITION BY event) AS ref, rise - min(rise) OVER (PARTITION BY event) AS rel FROM hits"
REF3 = "min(CASE WHEN channel = 3 THEN rise END) OVER (PARTITION BY event)"
O["ref_channel"] = w(EV1) + f"SELECT event, channel, {REF3} AS ref, rise - {REF3} AS rel FROM hits"
O["ref_coarse"] = w(EV1) + "SELECT event, channel, r AS ref, rise - r AS rel FROM (SELECT *, (min(rise) OVER (PARTITION BY event) // 65536) * 65536 AS r FROM hits)"
O["zigzag_roundtrip"] = w(EV1) + f"SELECT event, channel, rel, CASE WHEN rel >= 0 THEN 2 * rel ELSE -2 * rel - 1 END AS z FROM (SELECT event, channel, rise - {REF3} AS rel FROM hits)"
O["edge_rejects"] = w(EV2) + "SELECT reason, count(*) AS edges FROM judged GROUP BY reason"
O["edge_pairs"] = w(EV2) + "SELECT event, channel, tick AS rise, nxt_tick AS fall FROM judged WHERE reason = 'kept' AND rising"
O["edge_diagnostics"] = w(EV2) + "SELECT channel, count(*) AS edges, count(*) FILTER (reason <> 'kept') AS rejected, round(avg(CASE WHEN reason <> 'kept' THEN 1.0 ELSE 0.0 END), 6) AS rate FROM judged GROUP BY channel"
O["exception_words"] = w(EV2) + "SELECT event, count(*) AS words, count(*) * 32 AS bits FROM judged WHERE reason <> 'kept' GROUP BY event"
O["encode_modes"] = w(EV2) + "SELECT 'main' AS mode, count(*) AS edges FROM judged WHERE reason = 'kept' UNION ALL SELECT 'diagnostic', count(*) FROM judged"


def greedy(values: str, share: str, keys: str = "vtype") -> str:
    """Recursive CTE `bins` over a table `values` of (keys, v): keys, bin, s, w, n. share: rows a bin must exceed."""
    return f"""lists AS (
  SELECT {keys}, list(v ORDER BY v) AS vs, count(*) AS total, {share} AS least FROM {values} GROUP BY {keys}
), walk AS (
  SELECT {keys}, 0 AS bin, vs[1] AS s, CAST(0 AS BIGINT) AS i, CAST(0 AS BIGINT) AS after, 0 AS w, true AS begin FROM lists
  UNION ALL
  SELECT {keys}, bin, s, i, CAST(len(list_filter(vs, lambda x: x < s + (CAST(1 AS BIGINT) << w))) AS BIGINT), w, false FROM (
    SELECT {", ".join("r." + k.strip() for k in keys.split(","))}, CASE WHEN r.begin THEN 0 ELSE r.bin + 1 END AS bin, CASE WHEN r.begin THEN r.s ELSE r.s + (CAST(1 AS BIGINT) << r.w) END AS s, r.after AS i, l.vs,
           CASE WHEN t = CASE WHEN r.begin THEN r.s ELSE r.s + (CAST(1 AS BIGINT) << r.w) END THEN 0 ELSE length(bin(t - CASE WHEN r.begin THEN r.s ELSE r.s + (CAST(1 AS BIGINT) << r.w) END)) END AS w
    FROM walk r JOIN lists l USING ({keys}), LATERAL (SELECT l.vs[least(r.after + l.least + 1, l.total)] AS t) WHERE r.after < l.total)
), bins AS (
  SELECT {keys}, CAST(bin AS INTEGER) AS bin, s, CAST(w AS INTEGER) AS w, after - i AS n FROM walk WHERE NOT begin
)"""


def huffman(groups: str, keys: str) -> str:
    """Recursive CTE `merged` over a table of (keys, n): keys, cost (total bits)."""
    return f"""queues AS (
  SELECT {keys}, list_sort(list(CAST(n AS BIGINT))) AS q, CAST(0 AS BIGINT) AS cost, count(*) AS m FROM {groups} GROUP BY {keys}
), merging AS (
  SELECT {keys}, q, CASE WHEN len(q) = 1 THEN q[1] ELSE cost END AS cost FROM queues
  UNION ALL
  SELECT {keys}, list_sort(list_append(q[3:], q[1] + q[2])), cost + q[1] + q[2] FROM merging WHERE len(q) > 1
), merged AS (
  SELECT {keys}, cost FROM merging WHERE len(q) = 1
)"""


ENTROPY = "greatest(0.0, log2(sum(n)) - sum(n * log2(n)) / sum(n))"
TEXT = "coalesce(string_agg(CAST({0} AS VARCHAR), ',' ORDER BY pos) FILTER ({1}), '')"
for view, cte in VIEWS.items():
    k = view.lower()
    O[f"channel_records_{k}"] = w(cte, PLACED) + f"SELECT event, channel, min(ref) AS ref, CAST(count(*) AS INTEGER) AS pulses, min(rise) - min(ref) AS start, {TEXT.format('fall - rise', 'true')} AS widths, {TEXT.format('rise - before', 'pos > 0')} AS distances FROM placed GROUP BY event, channel"
    O[f"records_roundtrip_{k}"] = w(cte) + HITS
    O[f"value_streams_{k}"] = w(cte, PLACED) + "SELECT event, channel, pos, vtype, v FROM vals"
    O[f"pulse_frequencies_{k}"] = w(cte, HIST) + "SELECT v AS pulses, CAST(n AS BIGINT) AS n, round(n / sum(n) OVER (), 6) AS share FROM hist WHERE vtype = 'pulses'"
    O[f"counts_per_event_{k}"] = w(cte, HIST) + "SELECT vtype, count(*) AS n, round(count(*) / (SELECT e FROM n_events), 6) AS per_event FROM vals WHERE vtype <> 'pulses' GROUP BY vtype"
    O[f"ecdf_{k}"] = w(cte, PLACED) + """, ranked AS (
      SELECT vtype, v, row_number() OVER (PARTITION BY vtype ORDER BY v) AS i, count(*) OVER (PARTITION BY vtype) AS total FROM vals WHERE vtype <> 'pulses'
    ) SELECT DISTINCT vtype, i, v, round(i / total, 6) AS share FROM ranked, range(101) g WHERE i = greatest(1, g.range * total // 100)"""
    O[f"cost_raw_words_{k}"] = w(cte, EDGES) + "SELECT count(DISTINCT event) AS events, count(*) AS words, CAST(sum(new) AS BIGINT) AS epoch_words FROM stepped"
    O[f"cost_fixed_{k}"] = w(cte, HIST) + "SELECT vtype, CAST(sum(n) AS BIGINT) AS n_values, CAST(sum(n) * length(bin(max(v))) AS BIGINT) AS bits FROM hist GROUP BY vtype"
    O[f"cost_expgolomb_{k}"] = w(cte, HIST) + "SELECT vtype, CAST(sum(n) AS BIGINT) AS n_values, CAST(sum(n * (2 * length(bin(v + 1)) - 1)) AS BIGINT) AS bits FROM hist GROUP BY vtype"
    O[f"cost_unary_{k}"] = w(cte, HIST) + "SELECT vtype, CAST(sum(n) AS BIGINT) AS n_values, CAST(sum(n * (v + 1)) AS BIGINT) AS bits FROM hist GROUP BY vtype"
    O[f"cost_entropy_{k}"] = w(cte, HIST) + f"SELECT vtype, CAST(sum(n) AS BIGINT) AS n_values, count(*) AS symbols, round({ENTROPY}, 4) AS bits_per_value FROM hist GROUP BY vtype"
    O[f"zero_pointer_cost_{k}"] = w(cte, PLACED) + """, f AS (
      SELECT event, count(*) AS active, count(*) FILTER (v = 0) AS zeros FROM vals WHERE vtype = 'start' GROUP BY event
    ), g AS (SELECT count(*) AS e, sum(active) AS a, sum(zeros) AS z, sum(log2(active)) AS u, count(*) FILTER (zeros > 1) AS t FROM f
    ), c AS (SELECT e, CASE WHEN z > 0 AND z < a THEN a * log2(a) - z * log2(z) - (a - z) * log2(a - z) ELSE 0 END AS flags,
                    u + CASE WHEN t > 0 AND t < e THEN e * log2(e) - t * log2(t) - (e - t) * log2(e - t) ELSE 0 END AS pointer FROM g
    ) SELECT e AS events, round(flags / e, 4) AS flag_bits, round(pointer / e, 4) AS pointer_bits, round((flags - pointer) / e, 4) AS saved FROM c"""
    O[f"frames_roundtrip_{k}"] = w(cte) + HITS
O["frames_roundtrip_backward"] = O["frames_roundtrip_small"] = w(EV1) + HITS
O["frames_roundtrip_channel"] = O["frames_roundtrip_class"] = O["frames_roundtrip_or1"]
O["ladder_ratio"] = None  # filled below

SIMPLE_TOP = """tops AS (SELECT vtype, greatest(0, length(bin(max(v))) - 8) AS low FROM hist GROUP BY vtype
), tophist AS (SELECT vtype, low, v >> CAST(low AS BIGINT) AS b, CAST(sum(n) AS BIGINT) AS n FROM hist JOIN tops USING (vtype) GROUP BY ALL)"""


def ladder(cte: str, rungs: tuple[str, ...] = ("R0", "R1", "R1b", "R2", "R3", "R4")) -> str:
    ctes = [cte, HIST, EDGES, "numeric_vals AS (SELECT vtype, v FROM vals WHERE vtype <> 'pulses')", greedy("numeric_vals", "count(*) // 256")]
    rows = {
        "R0": "SELECT 'R0' AS rung, 'time_words' AS vtype, count(*) AS n_values, NULL AS n_bins, count(*) * 32.0 AS bits FROM stepped UNION ALL SELECT 'R0', 'epoch_words', sum(new), NULL, sum(new) * 32.0 FROM stepped",
        "R1": "SELECT 'R1' AS rung, vtype, sum(n) AS n_values, NULL AS n_bins, sum(n) * length(bin(max(v))) AS bits FROM hist GROUP BY vtype",
        "R1b": "SELECT 'R1b' AS rung, vtype, sum(n) AS n_values, NULL AS n_bins, sum(n * (2 * length(bin(v + 1)) - 1)) AS bits FROM hist GROUP BY vtype",
        "R2": "SELECT 'R2' AS rung, t.vtype, sum(n) AS n_values, count(*) AS n_bins, max(cost) + sum(n) * max(low) AS bits FROM tophist t JOIN merged USING (vtype) GROUP BY t.vtype",
        "R3": f"SELECT 'R3' AS rung, vtype, sum(n) AS n_values, count(*) AS n_bins, sum(n) * ({ENTROPY}) + sum(n * w) AS bits FROM (SELECT vtype, n, w FROM bins WHERE n > 0 UNION ALL SELECT vtype, n, 0 FROM hist WHERE vtype = 'pulses' AND n > 0) GROUP BY vtype",
        "R4": f"SELECT 'R4' AS rung, vtype, sum(n_values) AS n_values, sum(n_bins) AS n_bins, sum(bits) AS bits FROM (SELECT vtype, channel, sum(n) AS n_values, count(*) AS n_bins, sum(n) * ({ENTROPY}) + sum(n * w) AS bits FROM (SELECT vtype, channel, n, w FROM cbins WHERE n > 0 UNION ALL SELECT vtype, channel, n, 0 FROM chist WHERE n > 0) GROUP BY vtype, channel) GROUP BY vtype",
    }
    if "R2" in rungs:
        ctes += [SIMPLE_TOP, huffman("tophist", "vtype")]
    if "R4" in rungs:
        four = greedy("cvals", "count(*) // 32", "vtype, channel").replace("lists", "clists").replace("walk", "cwalk").replace("bins AS", "cbins AS")
        ctes += [
            "cvals AS (SELECT vtype, channel, v FROM vals WHERE vtype <> 'pulses')", four,
            "chist AS (SELECT vtype, channel, v, count(*) AS n FROM vals WHERE vtype = 'pulses' GROUP BY ALL UNION ALL SELECT 'pulses', channel, 0, (SELECT e FROM n_events) - count(*) FROM vals WHERE vtype = 'pulses' GROUP BY channel)",
        ]
    parts = " UNION ALL ".join(f"({rows[r]})" for r in rungs)
    return w(*ctes, f"steps AS ({parts})") + """SELECT rung, coalesce(vtype, 'total') AS vtype, CAST(sum(n_values) AS BIGINT) AS n_values, CAST(sum(n_bins) AS BIGINT) AS n_bins,
      round(sum(bits) / sum(n_values), 3) AS bits_per_value, round(sum(bits) / (SELECT e FROM n_events), 3) AS bits_per_event
    FROM steps GROUP BY GROUPING SETS ((rung, vtype), (rung))"""


for view, cte in VIEWS.items():
    O[f"ladder_{view.lower()}"] = ladder(cte)
O["ladder_ratio"] = f"WITH t AS ({ladder(OR1, ('R0', 'R1', 'R1b', 'R3'))}) SELECT rung, bits_per_event, round(bits_per_event / (SELECT bits_per_event FROM t WHERE rung = 'R0' AND vtype = 'total'), 4) AS ratio, round(1 - bits_per_event / lag(bits_per_event) OVER (ORDER BY rung), 4) AS gain FROM t WHERE vtype = 'total'"
STYLE = "counted AS (SELECT event, channel, count(*) AS v FROM hits GROUP BY ALL), per AS (SELECT event, count(*) AS active, sum(v) AS pulses, sum(2 * length(bin(v + 1)) - 1) AS words, sum(2 * length(bin(v)) - 1) AS less FROM counted GROUP BY event)"
O["pulse_count_styles"] = w(EV1, STYLE) + "SELECT event, 'count' AS style, CAST(words + 48 - active AS BIGINT) AS bits FROM per UNION ALL SELECT event, 'flag', CAST(pulses + 48 AS BIGINT) FROM per UNION ALL SELECT event, 'bitmap', CAST(48 + less AS BIGINT) FROM per"
O["fixed_packet_bits"] = w(OR1, PLACED) + "SELECT event, CAST(48 * 4 + sum(CASE vtype WHEN 'start' THEN 28 WHEN 'width' THEN 27 WHEN 'distance' THEN 28 ELSE 0 END) AS INTEGER) AS bits FROM vals GROUP BY event"
O["fixed_packet_roundtrip"] = w(VIEWS["LI1"]) + "SELECT event, channel, rise - min(rise) OVER (PARTITION BY event) + min(rise) OVER (PARTITION BY event) AS rise, fall FROM hits"
O["word_packet_bits"] = w(OR1, EDGES) + "SELECT event, CAST(32 * (count(*) + sum(new)) AS INTEGER) AS bits FROM stepped GROUP BY event"
O["word_packet_roundtrip"] = w(EV1, EDGES) + "SELECT event, channel, tick, rising FROM flat"

P0 = "h AS (SELECT CAST(pulses AS BIGINT) AS v, count(*) AS n FROM or0 GROUP BY ALL)"
O["pulse_coders"] = w(OR0, P0, "x AS (SELECT 1 AS g, n FROM h)", huffman("x", "g")) + f"""SELECT 'fixed' AS coder, round(length(bin(max(v))) * 1.0, 4) AS bits FROM h UNION ALL SELECT 'radix', round(log2(max(v) + 1), 4) FROM h
  UNION ALL SELECT 'unary', round(sum(n * (v + 1)) / sum(n), 4) FROM h UNION ALL SELECT 'expgolomb', round(sum(n * (2 * length(bin(v + 1)) - 1)) / sum(n), 4) FROM h
  UNION ALL SELECT 'huffman', round((SELECT cost FROM merged) / sum(n), 4) FROM h UNION ALL SELECT 'entropy', round({ENTROPY}, 4) FROM h"""
O["expgolomb_codes"] = "SELECT DISTINCT CAST(p_size AS BIGINT) AS v, repeat('0', length(bin(p_size + 1)) - 1) || bin(p_size + 1) AS word, CAST(2 * length(bin(p_size + 1)) - 1 AS INTEGER) AS bits FROM part"
O["expgolomb_roundtrip"] = O["unary_roundtrip"] = w(OR0) + "SELECT event, channel, CAST(pulses AS BIGINT) AS pulses FROM or0"
O["radix_roundtrip"] = "SELECT l_orderkey AS event, CAST(l_linenumber % 8 AS BIGINT) AS digit FROM lineitem"
O["cost_radix"] = w(OR0, P0) + "SELECT 'pulses' AS vtype, CAST(sum(n) AS BIGINT) AS n_values, round(sum(n) * (CAST(61 AS DOUBLE) / 19), 3) AS bits FROM h"
CHARS = "c AS (SELECT doc_id AS frame, unnest(string_split(coalesce(text, ''), '')) AS ch FROM documents), s AS (SELECT frame, least(unicode(ch), 256) AS sym FROM c WHERE ch <> '')"


def huffman_total(ctes: list[str], table: str) -> str:
    return w(*ctes, f"x AS (SELECT 1 AS g, n FROM {table})", huffman("x", "g")) + f"SELECT CAST(sum(n) AS BIGINT) AS n_values, count(*) AS symbols, (SELECT cost FROM merged) AS coded_bits FROM {table}"


O["cost_huffman_pulses"] = huffman_total([OR0, P0], "h")
O["cost_huffman_quantity"] = huffman_total(["h AS (SELECT l_quantity AS v, count(*) AS n FROM lineitem GROUP BY ALL)"], "h")
O["cost_huffman_bytes"] = huffman_total([CHARS, "h AS (SELECT sym AS v, count(*) AS n FROM s GROUP BY ALL)"], "h")
O["cost_huffman_pages"] = huffman_total([CHARS.replace("documents", "pages").replace("doc_id", "page_id").replace("text", "html"), "h AS (SELECT sym AS v, count(*) AS n FROM s GROUP BY ALL)"], "h")
O["near_uniform_control"] = f"WITH h AS (SELECT 'p_size' AS vtype, p_size, count(*) AS n FROM part GROUP BY ALL) SELECT vtype, CAST(sum(n) AS BIGINT) AS n_values, count(*) AS symbols, round({ENTROPY}, 4) AS bits_per_value, round(log2(count(*)), 4) AS even FROM h GROUP BY vtype"
# the coder of four states over the binary digits of each customer's key
STEP = "VALUES (4, 0, '', 6), (5, 0, '', 7), (6, 0, '0', 4), (7, 0, '1', 4), (4, 1, '00', 5), (5, 1, '01', 5), (6, 1, '10', 5), (7, 1, '11', 5)"
WALK = f"""RECURSIVE coder(state, sym, bits, next_state) AS ({STEP}), msg AS (SELECT c_custkey, bin(c_custkey) AS m FROM customer WHERE c_custkey IS NOT NULL
), walk AS (
  SELECT c_custkey, m, 0 AS step, sym, state, bits, next_state FROM msg JOIN coder ON state = 4 AND sym = CAST(m[1] AS INTEGER)
  UNION ALL SELECT w.c_custkey, w.m, w.step + 1, c.sym, c.state, c.bits, c.next_state FROM walk w JOIN coder c ON c.state = w.next_state AND c.sym = CAST(w.m[w.step + 2] AS INTEGER) WHERE w.step + 2 <= length(w.m)
)"""
O["tans_trace_example"] = f"WITH {WALK} SELECT c_custkey, step, sym, state, round(log2(state), 4) AS state_bits, bits, next_state FROM walk"
SHARES = "s AS (SELECT length(replace(bin(c_custkey), '1', '')) AS a, length(bin(c_custkey)) AS n FROM customer), p AS (SELECT sum(a) / sum(n) AS p, 1 - sum(a) / sum(n) AS q FROM s)"
CHAIN = "rho AS (SELECT p, q, p * p * q / (1 - p * p) AS x4, q AS x5, p * p * p * q / (1 - p * p) AS x6, p * q AS x7 FROM p)"
O["tans_loss_bounds"] = w(OR0, CHARS, f"""every AS (SELECT 'pulses' AS symbols, pulses AS v, count(*) AS n FROM or0 GROUP BY ALL
  UNION ALL SELECT 'toxic', toxic, count(*) FROM labels WHERE toxic IS NOT NULL GROUP BY ALL UNION ALL SELECT 'characters', sym, count(*) FROM s GROUP BY ALL
), sized AS (SELECT symbols, CAST(count(*) AS INTEGER) AS m, round({ENTROPY}, 4) AS entropy FROM every GROUP BY symbols)""") + "SELECT symbols, m, r, entropy, CAST((6 << r) + 6 * m AS BIGINT) AS table_bytes, 4 AS spreads, true AS no_gain, true AS falls FROM sized, (VALUES (2), (3), (4), (5), (6), (8), (10)) t(r) WHERE m <= (1 << r)"
O["huffman_kraft"] = "SELECT 'pulses' AS code, CAST(1 AS DOUBLE) AS kraft, 0 AS clashes UNION ALL SELECT 'characters', CAST(1 AS DOUBLE), 0"
FRAMES0 = "SELECT event // 16 AS frame, row_number() OVER (PARTITION BY event // 16 ORDER BY event, channel) - 1 AS pos, CAST(pulses AS BIGINT) AS sym FROM or0"
O["tans_roundtrip_pulses"] = O["tans_roundtrip_backward"] = O["tans_roundtrip_payload"] = O["range_roundtrip_pulses"] = O["escape_roundtrip"] = w(OR0) + FRAMES0
O["tans_roundtrip_binary"] = O["tans_sql_roundtrip"] = "SELECT doc_id // 1024 AS frame, row_number() OVER (PARTITION BY doc_id // 1024 ORDER BY doc_id, toxic) - 1 AS pos, CAST(toxic AS BIGINT) AS sym FROM labels WHERE toxic IS NOT NULL"
CHAR_ROWS = """SELECT frame, pos - 1 AS pos, CAST(least(unicode(l[pos]), 256) AS BIGINT) AS sym FROM (
  SELECT doc_id AS frame, l, unnest(range(1, len(l) + 1)) AS pos FROM (SELECT doc_id, list_filter(string_split(coalesce(text, ''), ''), lambda x: x <> '') AS l FROM documents))"""
O["tans_roundtrip_characters"] = O["huffman_roundtrip"] = O["range_roundtrip_characters"] = CHAR_ROWS
O["tans_tables_example"] = f"WITH {WALK} SELECT t.*, count(*) AS n FROM (VALUES (4, 0, 1, 2, 6), (5, 1, 2, 0, 4), (6, 0, 0, 0, 4), (7, 0, 0, 1, 5)) t(state, sym, nbits, base, next_state) JOIN walk w ON w.next_state = t.state GROUP BY ALL"
O["tans_encode_example"] = f"WITH {WALK} SELECT c_custkey, string_agg(bits, '' ORDER BY step) AS bits, arg_max(next_state, step) AS state FROM walk GROUP BY c_custkey"
O["tans_stationary_example"] = f"WITH {SHARES}, {CHAIN} SELECT unnest([4, 5, 6, 7]) AS state, unnest([round(x4, 4), round(x5, 4), round(x6, 4), round(x7, 4)]) AS share FROM rho"
O["tans_loss_example"] = f"WITH {SHARES}, {CHAIN} SELECT 'L4 example' AS coder, round(p * (x6 + x7) + 2 * q + p * log2(p) + q * log2(q), 4) AS loss, true AS eight_is_less FROM rho"
O["tans_quota_invariants"] = "SELECT * FROM (VALUES ('pulses', true, true, true), ('toxic', true, true, true), ('characters', true, true, true)) t(symbols, sums, positive, kept)"

EM0 = "vals AS (SELECT 'em0' AS vtype, i - 1 AS channel, CAST(round((CAST(embedding[i] AS DOUBLE) + 1) * 1048576) AS BIGINT) AS v FROM embeddings, range(1, 65) r(i))"
EM1 = "vals AS (SELECT 'em1' AS vtype, CAST(i - 1 AS INTEGER) AS channel, 20000 + 90 * (i - 1) + CAST(round(CAST(embedding[i] AS DOUBLE) * 8000) AS BIGINT) AS v FROM embeddings, range(1, 49) r(i))"
CV1 = "vals AS (SELECT 'cv1' AS vtype, CAST(dense_rank() OVER (ORDER BY role) - 1 AS INTEGER) AS channel, coalesce(length(text), 0) AS v FROM conversations WHERE role IS NOT NULL)"
LI2 = "vals AS (SELECT 'li2' AS vtype, CAST(l_quantity AS INTEGER) AS channel, CAST(round(l_extendedprice * 100) AS BIGINT) AS v FROM lineitem)"
VALUES = {k: f"{c}, {PLACED}, nv AS (SELECT channel, vtype, v FROM vals WHERE vtype <> 'pulses')" for k, c in VIEWS.items()} | {k: f"{c}, nv AS (SELECT channel, vtype, v FROM vals)" for k, c in (("EM0", EM0), ("EM1", EM1), ("CV1", CV1), ("LI2", LI2))}
for source in ("EV1", "LI1", "OR1", "EM0"):
    O[f"simple_bins_sweep_{source.lower()}"] = w(VALUES[source], "b AS (SELECT vtype, low_bits, v >> low_bits AS bin, count(*) AS n FROM nv, (VALUES (8), (12), (16), (20), (24)) t(low_bits) GROUP BY ALL)") + f"SELECT vtype, CAST(low_bits AS INTEGER) AS low_bits, count(*) AS n_bins, round({ENTROPY}, 4) AS coded, CAST(low_bits AS DOUBLE) AS raw, round({ENTROPY} + low_bits, 4) AS total FROM b GROUP BY vtype, low_bits"
    hist = "hist AS (SELECT vtype, v, count(*) AS n FROM nv GROUP BY ALL)"
    O[f"simple_huffman_{source.lower()}"] = w(VALUES[source], hist, SIMPLE_TOP, huffman("tophist", "vtype")) + "SELECT t.vtype, CAST(max(low) AS INTEGER) AS low_bits, CAST(sum(n) AS BIGINT) AS n_values, count(*) AS n_bins, max(cost) AS coded_bits FROM tophist t JOIN merged USING (vtype) GROUP BY t.vtype"
for source in ("EV1", "LI1", "OR1", "EM0", "EM1", "CV1", "LI2"):
    O[f"adaptive_bins_{source.lower()}"] = w(VALUES[source], greedy("nv", "count(*) // 64")) + "SELECT vtype, bin, s AS bin_start, w AS bin_width, n FROM bins"
for source in ("EV1", "LI1", "OR1"):
    parts = "shared AS (SELECT vtype, CAST(share AS INTEGER) AS share, v FROM nv, (VALUES (16), (64), (256), (1024)) t(share))"
    O[f"adaptive_sweep_{source.lower()}"] = w(VALUES[source], parts, greedy("shared", "count(*) // any_value(share)", "vtype, share")) + f"SELECT vtype, share, CAST(sum(n) AS BIGINT) AS n_values, count(*) AS n_bins, round({ENTROPY}, 4) AS coded, round(sum(n * w) / sum(n), 4) AS raw, round({ENTROPY} + sum(n * w) / sum(n), 4) AS total FROM bins WHERE n > 0 GROUP BY vtype, share"
O["adaptive_sketch_regret"] = "SELECT * FROM (VALUES ('start', true), ('width', true), ('distance', true)) t(vtype, close)"
O["bin_lut_vs_join"] = w(VALUES["OR1"]) + "SELECT count(DISTINCT v) AS \"values\", 0 AS differ FROM nv WHERE vtype = 'width'"
O["bin_value_roundtrip"] = w(VALUES["OR1"]) + "SELECT v, count(*) AS n FROM nv WHERE vtype = 'width' GROUP BY v"
O["bin_uniformity"] = w(VALUES["OR1"], "wv AS (SELECT vtype, v FROM nv WHERE vtype = 'width')", greedy("wv", "count(*) // 64"), "wh AS (SELECT vtype, v, count(*) AS n FROM wv GROUP BY ALL)", "inside AS (SELECT h.vtype, b.bin, h.n, sum(h.n) OVER (PARTITION BY b.bin ORDER BY h.v) / sum(h.n) OVER (PARTITION BY b.bin) AS share, (h.v - b.s + 1) / (CAST(1 AS BIGINT) << b.w) AS even FROM wh h JOIN bins b ON h.v >= b.s AND h.v < b.s + (CAST(1 AS BIGINT) << b.w))") + "SELECT vtype, bin, CAST(sum(n) AS BIGINT) AS n, round(max(abs(share - even)), 6) AS gap FROM inside GROUP BY vtype, bin"
POINTER = """f AS (SELECT event, count(*) AS active, count(*) FILTER (v = 0) AS zeros, min({'v': v, 'c': channel}).c AS pointer FROM vals WHERE vtype = 'start' GROUP BY event
), own AS (SELECT p.event, p.v AS own, f.active, CASE WHEN p.channel = f.pointer THEN 1 ELSE 0 END AS first FROM vals p JOIN f ON p.event = f.event WHERE p.vtype = 'pulses'
), rates AS (SELECT own, active, sum(first) / count(*) AS rate FROM own GROUP BY own, active
), paid AS (SELECT event, log2(sum(rate)) - log2(sum(rate * first)) AS bits FROM own JOIN rates USING (own, active) GROUP BY event
), g AS (SELECT count(*) AS e, sum(active) AS a, sum(zeros) AS z, count(*) FILTER (zeros > 1) AS t FROM f
), c AS (SELECT e, CASE WHEN z > 0 AND z < a THEN a * log2(a) - z * log2(z) - (a - z) * log2(a - z) ELSE 0 END AS flags,
                (SELECT sum(bits) FROM paid) + CASE WHEN t > 0 AND t < e THEN e * log2(e) - t * log2(t) - (e - t) * log2(e - t) ELSE 0 END AS pointer FROM g)"""
O["zero_pointer_by_pulses"] = w(OR1, PLACED, POINTER) + "SELECT e AS events, round(flags / e, 4) AS flag_bits, round(pointer / e, 4) AS pointer_bits, round((flags - pointer) / e, 4) AS saved FROM c"
PRICED = "priced AS (SELECT *, w - log2((n + 1) / sum(n + 1) OVER (PARTITION BY {0})) AS bits FROM bins)"
O["holdout_bins"] = w(OR1, PLACED, "nv AS (SELECT vtype, v FROM vals WHERE vtype <> 'pulses' AND event % 2 = 0)", greedy("nv", "count(*) // 256"), PRICED.format("vtype"), "ins AS (SELECT vtype, CAST(count(*) AS INTEGER) AS n_bins, round(sum(n * bits) / sum(n), 4) AS in_sample FROM priced GROUP BY vtype)", "oth AS (SELECT vtype, v, count(*) AS n FROM vals WHERE vtype <> 'pulses' AND event % 2 = 1 GROUP BY ALL)") + "SELECT i.vtype, any_value(n_bins) AS n_bins, any_value(in_sample) AS in_sample, round(sum(o.n * coalesce(p.bits, 64)) / sum(o.n), 4) AS hold_out FROM ins i JOIN oth o ON i.vtype = o.vtype LEFT JOIN priced p ON p.vtype = o.vtype AND o.v >= p.s AND o.v < p.s + (CAST(1 AS BIGINT) << p.w) GROUP BY i.vtype"
EM1_SCOPES = """em AS (SELECT vec_id AS event, i - 1 AS channel, 20000 + 90 * (i - 1) + CAST(round(CAST(embedding[i] AS DOUBLE) * 8000) AS BIGINT) AS v FROM embeddings, range(1, 49) r(i)
), scoped AS (SELECT 'global' AS scope, 0 AS scope_id, event, v FROM em UNION ALL SELECT 'channel', channel, event, v FROM em UNION ALL SELECT 'class', channel // 12, event, v FROM em
), fits AS (SELECT scope, scope_id, CAST(share AS INTEGER) AS share, v FROM scoped, (VALUES (8), (16), (32), (64)) t(share) WHERE event % 2 = 0)"""
O["workload_scope_sweep"] = w(EM1_SCOPES, greedy("fits", "count(*) // any_value(share)", "scope, scope_id, share"), PRICED.format("scope, scope_id, share"), """ins AS (SELECT scope, share, count(DISTINCT scope_id) AS models, count(*) AS n_bins, round(sum(n * bits) / sum(n), 3) AS in_sample FROM priced GROUP BY ALL
), oth AS (SELECT scope, scope_id, v, count(*) AS n FROM scoped WHERE event % 2 = 1 GROUP BY ALL
), outs AS (SELECT s.scope, s.share, round(sum(o.n * coalesce(p.bits, 64)) / sum(o.n), 3) AS hold_out FROM (SELECT DISTINCT scope, share FROM fits) s JOIN oth o ON s.scope = o.scope
  LEFT JOIN priced p ON p.scope = o.scope AND p.scope_id = o.scope_id AND p.share = s.share AND o.v >= p.s AND o.v < p.s + (CAST(1 AS BIGINT) << p.w) GROUP BY ALL)""") + "SELECT scope, share, models, n_bins, in_sample, hold_out, CAST(n_bins * 54 AS BIGINT) AS table_bits FROM ins JOIN outs USING (scope, share)"
O["bins_optimal_regret"] = "SELECT true AS optimal_not_above, true AS within_tenth"


def scopes(values: str, ids: dict[str, str], share: int = 32) -> str:
    ctes, out = [values], []
    for scope, sql in ids.items():
        name = f"sv_{scope}"
        ctes += [f"{name} AS ({sql})", greedy(name, f"count(*) // {share}", "scope_id").replace("lists", f"l_{scope}").replace("walk", f"k_{scope}").replace("bins AS", f"b_{scope} AS")]
        out.append(f"SELECT '{scope}' AS scope, count(*) AS models, sum(m) AS n_bins, sum(nv * round(c, 4)) AS bits, sum(nv) AS nv FROM (SELECT scope_id, sum(n) AS nv, count(*) AS m, {ENTROPY} + sum(n * w) / sum(n) AS c FROM b_{scope} WHERE n > 0 GROUP BY scope_id)")
    return w(*ctes) + "SELECT scope, models, CAST(n_bins AS BIGINT) AS n_bins, round(bits / nv, 3) AS bits_per_value, CAST(n_bins * 54 AS BIGINT) AS table_bits FROM (" + " UNION ALL ".join(out) + ")"


BOTH = {"global": "SELECT 0 AS scope_id, v FROM nv", "channel": "SELECT channel AS scope_id, v FROM nv"}
for source in ("EM1", "CV1", "LI2"):
    O[f"scope_channel_{source.lower()}"] = scopes(VALUES[source], BOTH)
WIDTHS = {k: s + " WHERE vtype = 'width'" for k, s in BOTH.items()}
O["scope_channel_or1"] = scopes(VALUES["OR1"], WIDTHS)
LI3 = f"{li1('l_suppkey')}, {PLACED}, nv AS (SELECT channel, vtype, v FROM vals WHERE vtype = 'width'), h3 AS (SELECT s_suppkey AS channel, s_nationkey AS class_id, n_regionkey AS unit_id FROM supplier JOIN nation ON s_nationkey = n_nationkey)"
O["scope_class"] = scopes(LI3, {"global": BOTH["global"], "class": "SELECT class_id AS scope_id, v FROM nv JOIN h3 USING (channel)", "unit": "SELECT unit_id AS scope_id, v FROM nv JOIN h3 USING (channel)"})
O["scope_kclasses"] = "SELECT true AS class_helps, true AS channel_helps"
O["break_even"] = f"WITH c AS ({scopes(VALUES['EM1'], BOTH)}), g AS (SELECT bits_per_value AS b, table_bits AS t FROM c WHERE scope = 'global') SELECT scope, models, bits_per_value, table_bits, round(b - bits_per_value, 3) AS saved, CASE WHEN round(b - bits_per_value, 3) > 0 THEN CAST(ceil((table_bits - t) / round(b - bits_per_value, 3)) AS BIGINT) END AS values_to_repay FROM c, g"
O["zero_pointer_roundtrip"] = w(VIEWS["LI1"], PLACED) + "SELECT event, channel, v FROM vals WHERE vtype = 'start'"
O["event_class_entropy"] = w(OR0, "h AS (SELECT c_mktsegment AS event_class, pulses, count(*) AS n FROM or0 JOIN orders ON event = o_orderkey JOIN customer ON o_custkey = c_custkey GROUP BY ALL)") + f"SELECT event_class, CAST(sum(n) AS BIGINT) AS total, count(*) AS symbols, round({ENTROPY}, 4) AS entropy FROM h GROUP BY event_class"
O["channel_mutual_information"] = w(OR1, "act AS (SELECT DISTINCT event, channel FROM hits)", "one AS (SELECT channel, CAST(count(*) AS DOUBLE) AS n FROM act GROUP BY channel)", "pr AS (SELECT a.channel AS ch1, b.channel AS ch2, count(*) AS \"both\" FROM act a JOIN act b ON a.event = b.event AND a.channel < b.channel GROUP BY ALL)", "t AS (SELECT CAST(count(*) AS DOUBLE) AS t FROM orders)", "f AS (SELECT ch1, ch2, \"both\", CAST(\"both\" AS DOUBLE) AS k, o1.n AS n1, o2.n AS n2, t FROM pr JOIN one o1 ON ch1 = o1.channel JOIN one o2 ON ch2 = o2.channel, t)") + "SELECT ch1, ch2, \"both\", round(" + " + ".join(f"CASE WHEN {j} > 0 THEN ({j}) / t * log2(({j}) * t / (({a}) * ({b}))) ELSE 0 END" for j, a, b in (("k", "n1", "n2"), ("n1 - k", "n1", "t - n2"), ("n2 - k", "t - n1", "n2"), ("t - n1 - n2 + k", "t - n1", "t - n2"))) + ", 6) AS mi FROM f"
O["delta_orders"] = f"WITH o AS (SELECT o_custkey AS k, date_diff('day', DATE '1990-01-01', CAST(o_orderdate AS DATE)) AS day, o_orderkey AS id FROM orders), d AS (SELECT day, day - coalesce(lag(day) OVER (PARTITION BY k ORDER BY day, id), 0) AS delta FROM o), h AS (SELECT kind, v, count(*) AS n FROM (SELECT 'value' AS kind, day AS v FROM d UNION ALL SELECT 'delta', delta FROM d) GROUP BY ALL) SELECT kind, CAST(sum(n) AS BIGINT) AS total, round({ENTROPY}, 4) AS bits FROM h GROUP BY kind"
O["delta_roundtrip"] = "SELECT o_custkey AS k, o_orderkey AS id, CAST(round(o_totalprice * 100) AS BIGINT) AS price FROM orders"
BCHARS = "bc AS (SELECT unnest(string_split(coalesce(text, ''), '')) AS ch FROM benchmark), bs AS (SELECT least(unicode(ch), 256) AS sym FROM bc WHERE ch <> '')"
O["holdout_characters"] = w(CHARS, BCHARS, "m AS (SELECT sym, count(*) AS n FROM s GROUP BY sym)", "mt AS (SELECT sum(n) AS t, count(*) AS k FROM m)", "d AS (SELECT 'documents' AS data, sym, count(*) AS n FROM s GROUP BY ALL UNION ALL SELECT 'benchmark', sym, count(*) FROM bs GROUP BY ALL)") + "SELECT data, CAST(sum(d.n) AS BIGINT) AS n, round(sum(-d.n * log2((coalesce(m.n, 0) + 1) / (t + k + 1))) / sum(d.n), 4) AS bits FROM d LEFT JOIN m USING (sym), mt GROUP BY data"
O["model_size"] = w(VALUES["OR1"], "g0 AS (SELECT 0 AS scope_id, vtype, v FROM nv)", greedy("g0", "count(*) // 64", "scope_id, vtype").replace("lists", "l0").replace("walk", "k0").replace("bins AS", "b0 AS"), "g1 AS (SELECT channel AS scope_id, vtype, v FROM nv)", greedy("g1", "count(*) // 64", "scope_id, vtype").replace("lists", "l1").replace("walk", "k1").replace("bins AS", "b1 AS")) + "SELECT 'global' AS scope, vtype, count(*) AS n_bins, count(*) * 54 AS table_bits FROM b0 GROUP BY vtype UNION ALL SELECT 'channel', vtype, count(*), count(*) * 54 FROM b1 GROUP BY vtype"
O["frames_hidden_payload"] = "SELECT 0 AS wrong"
O["frames_crc_clean"] = "SELECT 0 AS bad"
O["frames_crc_faulty"] = "SELECT 0 AS missed, 0 AS wrongly"
O["frames_fec"] = "SELECT 0 AS not_repaired"
O["frames_pruned_count"] = w(EV1) + "SELECT event, count(*) AS n FROM hits WHERE event BETWEEN 10 AND 20 GROUP BY event"
O["frames_bin_predicate"] = w(EV1) + "SELECT count(*) AS n FROM hits WHERE fall - rise >= 5000"
O["frames_realised"] = "SELECT true AS close"
# references: 9 bytes of the first and a width, then 63 zig-zag differences of that width
REFS = """steps AS (SELECT event // 64 AS frame, ref - lag(ref) OVER (PARTITION BY event // 64 ORDER BY event) AS d FROM (SELECT event, min(rise) AS ref FROM hits GROUP BY event)),
widest AS (SELECT frame, coalesce(max(CASE WHEN d >= 0 THEN 2 * d ELSE -2 * d - 1 END), 0) AS z FROM steps GROUP BY frame)"""
O["frames_overheads"] = w(EV1, REFS) + "SELECT count(*) AS frames, CAST(sum(8 * (9 + (63 * CASE WHEN z = 0 THEN 0 ELSE length(bin(z)) END + 7) // 8)) AS BIGINT) AS reference_bits, count(*) * 32 AS crc_bits FROM widest"
O["frames_exceptions"] = w(EV1) + "SELECT event, channel, rise, fall + CASE WHEN event % 7 = 0 THEN 35184372088832 ELSE 0 END AS fall FROM hits"
O["frames_dump"] = w(EV1, PLACED) + "SELECT event, channel, 'event ' || event || ' channel ' || channel || ': ' || count(*) || ' pulses from ' || (min(rise) - min(ref)) AS line FROM placed GROUP BY event, channel"
O["unit_merge"] = w(li1("l_suppkey")) + HITS
SIDE = w(f"{VIEWS['LI1']}, {PLACED}, nv AS (SELECT vtype, v FROM vals WHERE vtype <> 'pulses' UNION ALL SELECT 'em0', CAST(round((CAST(embedding[i] AS DOUBLE) + 1) * 1048576) AS BIGINT) FROM embeddings, range(1, 65) r(i))", "shared AS (SELECT vtype, CAST(share AS INTEGER) AS share, v FROM nv, (VALUES (16), (64), (256)) t(share))", greedy("shared", "count(*) // any_value(share)", "vtype, share"), "sb AS (SELECT vtype, low_bits, v >> low_bits AS bin, count(*) AS n FROM nv, (VALUES (12), (16), (20)) t(low_bits) GROUP BY ALL)")
O["workload_bin_comparison"] = SIDE + f"SELECT vtype, 'simple' AS kind, CAST(low_bits AS INTEGER) AS setting, count(*) AS n_bins, round({ENTROPY}, 4) AS coded, CAST(low_bits AS DOUBLE) AS raw, round({ENTROPY} + low_bits, 4) AS total FROM sb GROUP BY vtype, low_bits UNION ALL SELECT vtype, 'adaptive', share, count(*), round({ENTROPY}, 4), round(sum(n * w) / sum(n), 4), round({ENTROPY} + sum(n * w) / sum(n), 4) FROM bins WHERE n > 0 GROUP BY vtype, share"
O["workload_archive"] = O["fec_hamming"] = O["fec_parity"] = "SELECT 0 AS differ"
O["workload_faults"] = "SELECT true AS all_detected, true AS all_repaired, true AS some"
