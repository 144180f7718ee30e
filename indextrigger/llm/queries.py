"""The queries of the operators in this subpackage, and SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import chat_format, chunk_dedup, cotraining, decontamination, hilbert_sharding, ngram_join, prefix_tokens, quality_rules, source_mixing, suffix_repeats


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_content_chunks": chunk_dedup.op1_content_chunks,
        "op2_source_mixing": source_mixing.op2_source_mixing,
        "op3_cotrained_quality": cotraining.op3_cotrained_quality,
        "op4_chat_formatting": chat_format.op4_chat_formatting,
        "op5_suffix_repeats": suffix_repeats.op5_suffix_repeats,
        "op6_token_counts": prefix_tokens.op6_token_counts,
        "op7_decontamination": decontamination.op7_decontamination,
        "op8_quality_rules": quality_rules.op8_quality_rules,
        "op9_ngram_jaccard": ngram_join.op9_ngram_jaccard,
        "op10_hilbert_sharding": hilbert_sharding.op10_hilbert_sharding,
        "quality_base_counts": quality_rules.quality_base_counts,
    }


_LOWERED = "translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

#: The template: a mark before the role, one before the text, one after it; backslash and the start of marks are escaped.
OP4_SQL = r"""
WITH t AS (SELECT conv_id, CAST(turn AS BIGINT) AS turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, k, CASE k WHEN 0 THEN 'user' ELSE 'assistant' END, '\### Assistant: </turn> ok' FROM range(2) r(k)),
e AS (SELECT *, replace(replace(role, '\', '\\'), '<|', '<\|') AS role_, replace(replace(text, '\', '\\'), '<|', '<\|') AS text_ FROM t),
g AS (SELECT conv_id, count(*) AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (role = 'assistant'), '') AS loss, CAST(sum(23 + length(role_) + length(text_)) AS BIGINT) AS formatted_chars FROM e GROUP BY conv_id)
SELECT conv_id, n_turns, turns_sha256, length(loss) AS loss_chars, sha256(loss) AS loss_sha256, formatted_chars FROM g
"""

OP7_SQL = rf"""
WITH d AS (SELECT doc_id, coalesce(regexp_extract_all({_LOWERED}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+'), []) AS ws FROM documents),
b AS (SELECT CAST(item_id AS VARCHAR) AS item, regexp_extract_all({_LOWERED}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM benchmark),
w AS (SELECT DISTINCT item, least(len(ws), 10) AS n, array_to_string(list_slice(ws, i, i + least(len(ws), 10) - 1), ' ') AS span FROM b, unnest(range(1, len(ws) - least(len(ws), 10) + 2)) r(i) WHERE len(ws) > 0),
p AS (SELECT doc_id, n, i, array_to_string(list_slice(ws, i, i + n - 1), ' ') AS span FROM d, (SELECT DISTINCT n FROM w), unnest(range(1, greatest(len(ws) - n + 2, 1))) r(i)),
h AS (SELECT doc_id, n, i, item FROM p JOIN w USING (n, span)),
c AS (SELECT doc_id, count(DISTINCT spot) AS n_hit FROM h, unnest(range(i, i + n)) r(spot) GROUP BY doc_id),
m AS (SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS items FROM (SELECT DISTINCT doc_id, item FROM h) GROUP BY doc_id)
SELECT doc_id, len(ws) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN c USING (doc_id) LEFT JOIN m USING (doc_id)
"""

OP9_SQL = rf"""
WITH RECURSIVE d AS (SELECT doc_id, coalesce(regexp_extract_all({_LOWERED}, '[^\x20\x09-\x0D]+'), []) AS ws FROM documents),
s AS (SELECT DISTINCT doc_id, array_to_string(list_slice(ws, i, i + 2), ' ') AS sh FROM d, unnest(range(1, greatest(len(ws) - 1, 2))) r(i) WHERE len(ws) > 0),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
l AS (SELECT a, b FROM (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS c FROM s x JOIN s y ON x.sh = y.sh AND x.doc_id <> y.doc_id GROUP BY 1, 2) JOIN n p ON p.doc_id = a JOIN n q ON q.doc_id = b WHERE 100 * c >= 90 * (p.n + q.n - c)),
r AS (SELECT a, b FROM l UNION SELECT r.a, l.b FROM r JOIN l ON r.b = l.a)
SELECT doc_id, coalesce(n, 0) AS n_shingles, least(doc_id, coalesce((SELECT min(b) FROM r WHERE r.a = d.doc_id), doc_id)) AS component_id FROM d LEFT JOIN n USING (doc_id)
"""


#: The counts and the base verdict of operator 8, which need no model.
BASE_COUNTS_SQL = r"""WITH d AS (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS t, coalesce(regexp_extract_all(text, '[^\x20\x09-\x0D]+'), []) AS ws FROM documents),
w AS (SELECT r, i, array_to_string(list_slice(ws, i, i + 2), ' ') AS s FROM d, unnest(range(1, greatest(len(ws) - 1, 1))) x(i)),
c AS (SELECT r, count(DISTINCT spot) AS n FROM (SELECT r, i, count(*) OVER (PARTITION BY r, s) AS m FROM w), unnest(range(i, i + 3)) y(spot) WHERE m > 1 GROUP BY r),
l AS (SELECT r, count(*) - count(DISTINCT line) AS n FROM (SELECT r, unnest(string_split(t, chr(10))) AS line FROM d) WHERE regexp_matches(line, '[^\x20\x09-\x0D]') GROUP BY r)
SELECT doc_id, len(ws) AS n_words, CAST(coalesce(list_sum(list_transform(ws, lambda x: length(x))), 0) AS BIGINT) AS word_chars, length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')) AS n_symbols,
 coalesce(l.n, 0) AS n_dup_lines, coalesce(c.n, 0) AS n_repeat_words, len(ws) < 50 OR 100 * coalesce(c.n, 0) > 50 * len(ws) AS base_failed FROM d LEFT JOIN c USING (r) LEFT JOIN l USING (r)
"""


def oracle_sql() -> dict[str, str]:
    return {"op2_source_mixing": source_mixing.OP2_SQL, "op4_chat_formatting": OP4_SQL, "op7_decontamination": OP7_SQL, "op9_ngram_jaccard": OP9_SQL, "quality_base_counts": BASE_COUNTS_SQL}
