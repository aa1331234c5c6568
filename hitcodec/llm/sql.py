"""DuckDB SQL with the results of the queries of this subpackage."""

from __future__ import annotations

URL = r"""
WITH cut AS (
  SELECT page_id, CASE WHEN instr(url, '://') > 0 THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages
), host AS (
  SELECT page_id, rest, coalesce(regexp_extract(rest, '^[^/?#]*'), '') AS raw FROM cut
), parts AS (
  SELECT page_id, translate(raw, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
         coalesce(regexp_extract(substr(rest, length(raw) + 1), '^[^?#]*'), '') AS path
  FROM host
), rules(rule_host, rule_path, rule, kind) AS (
  VALUES ('net', '/', 'net/', 'block'), ('example.net', '/en/', 'example.net/en/', 'allow'),
         ('example.com', '/de/', 'example.com/de/', 'block'), ('org', '/fr/', 'org/fr/', 'allow')
), hits AS (
  SELECT p.*, r.rule, r.kind FROM parts p JOIN rules r
    ON (p.host = r.rule_host OR p.host LIKE '%.' || r.rule_host) AND starts_with(p.path, r.rule_path)
), best AS (
  SELECT page_id, host, path, arg_max(rule, length(rule)) AS rule, arg_max(kind, length(rule)) AS kind FROM hits GROUP BY ALL
)
SELECT p.page_id, p.host, p.path, b.rule, coalesce(b.kind, 'allow') AS verdict
FROM parts p LEFT JOIN best b ON p.page_id = b.page_id AND p.host = b.host AND p.path = b.path
"""

LINES = r"""
WITH rows AS (
  SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS l FROM documents
), each AS (
  SELECT doc_id, unnest(l) AS line, generate_subscripts(l, 1) AS pos FROM rows
), keyed AS (
  SELECT doc_id, pos, line, translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS k FROM each
), shared AS (
  SELECT k, min(doc_id) AS first FROM keyed WHERE length(k) >= 10 GROUP BY k HAVING count(DISTINCT doc_id) > 1
), marked AS (
  SELECT e.doc_id, e.pos, e.line, coalesce(e.doc_id <> s.first, false) AS gone FROM keyed e LEFT JOIN shared s ON e.k = s.k
)
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (gone) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (NOT gone), '')) AS kept_sha256
FROM marked GROUP BY doc_id
"""

JACCARD = r"""
WITH RECURSIVE words AS (
  SELECT doc_id, regexp_extract_all(lower(coalesce(text, '')), '[\p{L}\p{N}_]+') AS l FROM documents
), grams AS (
  SELECT DISTINCT doc_id, array_to_string(l[i:i + least(len(l), 5) - 1], ' ') AS gram
  FROM (SELECT doc_id, l, unnest(range(1, greatest(len(l) - 4, 1) + 1)) AS i FROM words WHERE len(l) > 0)
), sizes AS (
  SELECT doc_id, count(*) AS n FROM grams GROUP BY doc_id
), common AS (
  SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS k FROM grams a JOIN grams b ON a.gram = b.gram AND a.doc_id <> b.doc_id GROUP BY ALL
), links AS (
  SELECT x, y FROM common JOIN sizes sx ON x = sx.doc_id JOIN sizes sy ON y = sy.doc_id WHERE k >= 0.8 * (sx.n + sy.n - k) - 1e-9
), reach AS (
  SELECT doc_id AS x, doc_id AS y FROM documents UNION SELECT r.x, l.y FROM reach r JOIN links l ON r.y = l.x
), degree AS (
  SELECT x, count(*) AS n FROM links GROUP BY x
)
SELECT r.x AS doc_id, min(r.y) AS class_id, coalesce(max(d.n), 0) AS n_links FROM reach r LEFT JOIN degree d ON r.x = d.x GROUP BY r.x
"""


def _draw(seed: str, turn: int) -> str:
    return f"((((({seed}) % 2147483647) * 48271 + {turn} * 69621 + 11) % 2147483647 * 48271) % 2147483647 * 16807 + 97) % 2147483647"


def _permuted(rounds: int) -> tuple[str, str]:
    """CTEs that send x through the bijection of [0, n), step by step; and the last one's name."""
    parts, last = [], "ask"
    for turn in range(2 * rounds):
        if turn % 2 == 0:
            step = f"(x + {_draw('seed', turn)}) % n"
        else:
            mixed = f"((x * ((({_draw('seed', turn)}) % 33554432) * 2 + 1)) & (top - 1))"
            step = f"CASE WHEN x < top THEN xor({mixed}, {mixed} >> half) ELSE x END"
        parts.append(f"step{turn} AS (SELECT rn, i, n, seed, top, half, {step} AS x FROM {last})")
        last = f"step{turn}"
    return ",\n".join(parts), last


_STEPS, _LAST = _permuted(4)
_FIRST, _SECOND = _draw("pos + 1", 5), _draw("xor(f, f >> 13)", 7)
MIX = rf"""
WITH sized AS (
  SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS size, (coalesce(doc_id, 0) % 1000003) * 40503 % 1024 AS bucket FROM documents
), per AS (
  SELECT source, CAST(sum(size) AS BIGINT) AS source_size, row_number() OVER (ORDER BY source NULLS LAST) AS rn FROM sized GROUP BY source
), weighed AS (
  SELECT *, (rn - 1) % 3 + 1 AS weight FROM per
), levels AS (
  SELECT *, ((SELECT sum(source_size) FROM weighed) - coalesce(sum(3 * source_size) OVER (o ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
            / sum(weight) OVER (o ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level
  FROM weighed WINDOW o AS (ORDER BY 3 * source_size / weight, rn)
), aims AS (
  SELECT *, CAST(CASE WHEN 3 * source_size <= level * weight THEN 3 * source_size
                      ELSE least(weight * (SELECT max(level) FROM levels WHERE NOT 3 * source_size <= level * weight), 3 * source_size) END AS DOUBLE) AS target FROM levels
), size_of AS (
  SELECT min(b) AS block FROM (VALUES (4), (8), (16), (32), (64), (128), (256), (512), (1024)) t(b), (SELECT coalesce(sum(source_size), 0) AS total FROM aims) WHERE b = 1024 OR b * 1048576 >= total
), plan AS (
  SELECT *, (source_size + block - 1) // block AS blocks FROM aims, size_of
), due AS (
  SELECT *, CASE WHEN blocks > 0 THEN target * blocks / source_size ELSE 0.0::DOUBLE END AS draws FROM plan
), line AS (
  SELECT *, CAST(round(coalesce(sum(draws) OVER (ORDER BY rn ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) / nullif(sum(draws) OVER (), 0), 0) * 1099511627776) AS BIGINT) AS high FROM due
), spans AS (
  SELECT rn, blocks, coalesce(lag(high) OVER (ORDER BY rn), 0) AS low, high FROM line
), total AS (
  SELECT CAST(coalesce(round(sum(draws)), 0) AS BIGINT) AS slots FROM due
), made AS (
  SELECT pos, pos // 4096 AS shard, pos % 4096 AS j, least(4096, slots - pos // 4096 * 4096) AS size FROM (SELECT slots, unnest(range(0, slots)) AS pos FROM total)
), first_draw AS (
  SELECT *, {_FIRST} AS f FROM made
), points AS (
  SELECT shard, j, ((j << 40) + (({_SECOND}) << 9)) // size AS point FROM first_draw
), drawn AS (
  SELECT p.shard, p.j, s.rn, s.blocks FROM points p JOIN spans s ON p.point >= s.low AND p.point < s.high
), ranked AS (
  SELECT rn, blocks, row_number() OVER (PARTITION BY rn ORDER BY shard, j) - 1 AS i FROM drawn
), ask AS (
  SELECT rn, i % blocks AS i, blocks AS n, rn * 7919 + (i // blocks) * 104729 + 1 AS seed, CAST(1 AS BIGINT) << (length(bin(blocks)) - 1) AS top,
         greatest(1, length(bin(blocks)) - length(bin(blocks)) // 2) AS half, i % blocks AS x
  FROM ranked WHERE i // blocks < 3
), {_STEPS}, used AS (
  SELECT rn, x AS block, count(*) AS uses FROM {_LAST} GROUP BY ALL
), placed AS (
  SELECT s.*, p.rn, p.source_size, p.target, p.block AS words,
         CAST(sum(size) OVER (PARTITION BY p.rn ORDER BY bucket, doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS BIGINT) - size AS origin
  FROM sized s JOIN plan p ON s.source IS NOT DISTINCT FROM p.source
), pieces AS (
  SELECT doc_id, rn, b AS block, least(origin + size, (b + 1) * words) - greatest(origin, b * words) AS held
  FROM (SELECT *, unnest(range(origin // words, (origin + size - 1) // words + 1)) AS b FROM placed WHERE size > 0)
), sums AS (
  SELECT doc_id, CAST(sum(held * uses) AS BIGINT) AS taken FROM pieces JOIN used USING (rn, block) GROUP BY doc_id
)
SELECT doc_id, size, source_size, target, coalesce(taken, 0) AS taken, source FROM placed LEFT JOIN sums USING (doc_id)
"""

ORACLES = {"op1_source_mixing": MIX, "op7_ngram_join": JACCARD, "op9_line_dedup": LINES, "op10_url_filter": URL}
