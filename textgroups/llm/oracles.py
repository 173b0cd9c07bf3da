"""DuckDB SQL for the operators that SQL can express. The others are tested against brute force."""

from __future__ import annotations

from textgroups.llm import license_scan, mixing, quality, sharding

WORD = r"[^\x20\x09-\x0D]+"


def mixing_sql() -> str:
    w5, w2, w1 = mixing.WEIGHTS
    b = mixing.BLOCK_WORDS
    return f"""
WITH d AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '{WORD}'))::BIGINT AS size FROM documents),
s AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM d GROUP BY source),
w AS (SELECT *, CASE (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 WHEN 0 THEN {w5} WHEN 1 THEN {w2} ELSE {w1} END AS weight FROM s),
r AS (SELECT *, sum(source_size) OVER () AS total, sum(weight) OVER () AS all_w, coalesce(sum(source_size) OVER o, 0) AS full_s, coalesce(sum(weight) OVER o, 0) AS full_w FROM w
  WINDOW o AS (ORDER BY source_size::DOUBLE / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
l AS (SELECT *, (total::DOUBLE * {mixing.FACTOR} - full_s::DOUBLE * {mixing.CAP}) / (all_w - full_w)::DOUBLE AS level FROM r),
water AS (SELECT level FROM l WHERE level * weight <= source_size * {mixing.CAP} ORDER BY source_size::DOUBLE / weight LIMIT 1),
t AS (SELECT source, source_size, least(coalesce((SELECT level FROM water) * weight, source_size * 2.0::DOUBLE), source_size * 2.0::DOUBLE) AS target FROM l),
p AS (SELECT d.*, t.source_size, t.target, coalesce(sum(size) OVER (PARTITION BY d.source ORDER BY md5('mix#' || d.doc_id), d.doc_id, d.size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS start FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source),
q AS MATERIALIZED (SELECT *, row_number() OVER () AS rid FROM p),
sh AS (SELECT source, floor(target)::BIGINT AS words, ceil(floor(target) / {b})::BIGINT AS blocks, (upto - target) / al AS low, CASE WHEN upto >= al THEN 2.0::DOUBLE ELSE upto / al END AS high
  FROM (SELECT source, target, sum(target) OVER (ORDER BY source NULLS LAST ROWS UNBOUNDED PRECEDING) AS upto, sum(target) OVER () AS al FROM t) WHERE floor(target) > 0),
pt AS (SELECT k, x - floor(x) AS u FROM (SELECT k, (k + 0.5::DOUBLE) * {mixing.GOLDEN}::DOUBLE AS x FROM (SELECT unnest(range(CAST((SELECT sum(blocks) FROM sh) AS BIGINT))) AS k))),
ht AS (SELECT k AS slot, source, blocks, row_number() OVER (PARTITION BY source ORDER BY k) - 1 AS rank FROM pt JOIN sh ON u >= low AND u < high QUALIFY rank < blocks),
sl AS (SELECT slot, source, rank FROM ht UNION ALL
  SELECT row_number() OVER (ORDER BY rank, CASE WHEN source IS NULL THEN '-' ELSE '=' || source END) - 1 + (SELECT CAST(sum(blocks) AS BIGINT) FROM sh), source, rank
  FROM (SELECT sh.source, unnest(range(coalesce(g.n, 0), sh.blocks)) AS rank FROM sh LEFT JOIN (SELECT source, count(*) AS n FROM ht GROUP BY source) g ON g.source IS NOT DISTINCT FROM sh.source)),
pc AS (SELECT rid, source, unnest(range(CAST(lo // {b} AS BIGINT), CAST((hi - 1) // {b} + 1 AS BIGINT))) AS rank FROM (SELECT rid, source, start + pass * source_size AS lo, least(start + pass * source_size + size, floor(target)::BIGINT) AS hi FROM q CROSS JOIN (SELECT unnest([0, 1]) AS pass)) WHERE lo < hi),
fs AS (SELECT rid, min(slot) AS first_slot FROM pc JOIN sl ON sl.rank = pc.rank AND sl.source IS NOT DISTINCT FROM pc.source GROUP BY rid)
SELECT doc_id, size, source_size, target, source, fs.first_slot,
  CAST(greatest(0, least(start + size, floor(target)::BIGINT) - start) + greatest(0, least(start + source_size + size, floor(target)::BIGINT) - start - source_size) AS BIGINT) AS taken FROM q LEFT JOIN fs USING (rid)"""


def license_sql() -> str:
    names = ", ".join(f"'{s}': '{n}'" for n, s in license_scan.SENTENCES.items())
    steps = []
    for i, (name, ids) in enumerate(license_scan.in_order()):
        steps.append(f"t{i + 1} AS (SELECT doc_id, ids, replace(line, '{ids}', ' | ') AS line, CASE WHEN contains(line, '{ids}') THEN list_append(found, '{name}') ELSE found END AS found FROM t{i})")
    return f"""
WITH s AS (SELECT doc_id, list_transform(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\\n\\r]+|[.!?]+[ \\t]+|[.!?]+$'),
  lambda x: rtrim(trim(regexp_replace(x, '{license_scan.NOISE}', ' ', 'g')), ' .')) AS ss FROM documents),
k AS (SELECT doc_id, list_filter(list_transform(ss, lambda x: map_extract_value(MAP {{{names}}}, x)), lambda i: i IS NOT NULL) AS ids FROM s),
t0 AS (SELECT doc_id, ids, ' ' || array_to_string(ids, ' ') || ' ' AS line, []::VARCHAR[] AS found FROM k),
{", ".join(steps)}
SELECT doc_id, array_to_string(ids, ' ') AS sentence_ids, array_to_string(list_sort(list_distinct(found)), ',') AS licenses, len(list_distinct(found))::BIGINT AS n_licenses FROM t{len(steps)}"""


def sharding_sql() -> str:
    table = sharding.fill_table(sharding.shard_names())
    return f"""
WITH s AS (SELECT doc_id, ('0x' || substr(md5(coalesce(doc_id::VARCHAR, '')), 1, 15))::BIGINT % {sharding.SLOTS} AS slot FROM documents)
SELECT doc_id, slot, ({table}::INTEGER[])[slot + 1] AS shard FROM s"""


def quality_sql() -> str:
    return f"""
WITH d AS (SELECT row_number() OVER () AS row, doc_id, coalesce(text, '') AS text, regexp_extract_all(coalesce(text, ''), '{WORD}') AS ws FROM documents),
g AS (SELECT row, i, array_to_string(ws[i:i + 7], ' ') AS passage FROM (SELECT row, ws, unnest(range(1, len(ws) - 6)) AS i FROM d WHERE len(ws) >= 8)),
c AS (SELECT row, i FROM g QUALIFY count(*) OVER (PARTITION BY row, passage) > 1),
v AS (SELECT row, count(DISTINCT pos) AS n FROM (SELECT row, unnest(range(i, i + 8)) AS pos FROM c) GROUP BY row),
m AS (SELECT d.row, doc_id, len(ws)::BIGINT AS n_words, CAST(coalesce(list_sum(list_transform(ws, lambda x: length(x))), 0) AS BIGINT) AS word_chars,
  length(regexp_replace(text, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols,
  list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '{WORD}')) AS lines,
  coalesce(v.n, 0)::BIGINT AS n_repeat_words,
  len(list_filter(range(2, len(ws) + 1), lambda i: ws[i] = ws[i - 1])) AS n_same_next,
  length(regexp_replace(text, '\\P{{Lu}}', '', 'g')) AS n_upper, length(regexp_replace(text, '\\P{{L}}', '', 'g')) AS n_letters,
  len(list_filter(ws, lambda x: regexp_matches(x, '\\p{{L}}'))) AS n_alpha_words, length(regexp_replace(text, '[^!]', '', 'g')) AS n_marks
  FROM d LEFT JOIN v ON v.row = d.row),
n AS (SELECT *, (len(lines) - len(list_distinct(lines)))::BIGINT AS n_dup_lines, len(lines) AS n_lines FROM m),
f AS (SELECT *, (n_words < 20)::BIGINT + 2 * (100 * n_repeat_words > 30 * n_words)::BIGINT + 4 * (10 * n_symbols > n_words)::BIGINT + 8 * (n_lines >= 4 AND 100 * n_dup_lines > 30 * n_lines)::BIGINT
  + 16 * (word_chars > 20 * n_words)::BIGINT + 32 * (5 * n_same_next > n_words)::BIGINT + 64 * (10 * n_upper > 6 * n_letters)::BIGINT + 128 * (10 * n_alpha_words < 6 * n_words)::BIGINT + 256 * (4 * n_marks > n_words)::BIGINT AS failed FROM n)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, failed & 3 <> 0 AS base_failed, failed = 0 AS kept, failed FROM f"""


def ablations_sql() -> str:
    rules = ", ".join(f"('{r.name}', {1 << i})" for i, r in enumerate(quality.RULES))
    return f"""
WITH m AS ({quality_sql()})
SELECT rule, CAST(count(*) FILTER (failed & bit <> 0) AS BIGINT) AS failing, CAST(count(*) FILTER (failed = bit) AS BIGINT) AS failing_alone, CAST(count(*) FILTER (failed = bit OR failed = 0) AS BIGINT) AS kept_without
FROM m CROSS JOIN (VALUES {rules}) r(rule, bit) GROUP BY rule"""


def exact_dedup_sql() -> str:
    return """
WITH d AS (SELECT doc_id, length(coalesce(text, '')) AS n, sha256(regexp_replace(coalesce(text, ''), '[\\x20\\x09-\\x0D]', '', 'g')) AS h FROM documents)
SELECT doc_id, first_value(doc_id) OVER (PARTITION BY h ORDER BY n DESC, doc_id) AS keep_id, count(*) OVER (PARTITION BY h) AS group_size,
  row_number() OVER (PARTITION BY h ORDER BY n DESC, doc_id) = 1 AS kept, h AS text_sha256 FROM d"""


def oracle_sql() -> dict[str, str]:
    return {"op1_mixing": mixing_sql(), "op2_license_scan": license_sql(), "op4_sharding": sharding_sql(), "op5_quality_rules": quality_sql(), "op8_exact_dedup": exact_dedup_sql(), "quality_ablations": ablations_sql()}
