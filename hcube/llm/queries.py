"""Registered queries of this folder, and SQL for those that SQL can express."""

from __future__ import annotations

from .chat import CLOSE, MIDDLE, OPEN, TRAINED_ROLE, op2_preference_format
from .htmltext import op6_main_text
from .licences import op7_licence_scan
from .lm import op9_language_model
from .packing import op3_best_fit_packing
from .quality import DEFAULT_RULES, MAX_REPEAT_PERCENT, MIN_WORDS, STOP_WORDS, op8_quality_rules
from .sentencepieces import op10_sentencepiece
from .simhash import op1_simhash
from .suffix_dedup import op5_suffix_dedup
from .topk import K, SCALE, STRIDE, op4_exact_topk

_OPERATORS = {
    "op1_simhash": (op1_simhash, "documents"),
    "op2_preference_format": (op2_preference_format, "conversations"),
    "op3_best_fit_packing": (op3_best_fit_packing, "documents"),
    "op4_exact_topk": (op4_exact_topk, "embeddings"),
    "op5_suffix_dedup": (op5_suffix_dedup, "documents"),
    "op6_main_text": (op6_main_text, "pages"),
    "op7_licence_scan": (op7_licence_scan, "documents"),
    "op8_quality_rules": (op8_quality_rules, "documents"),
    "op9_language_model": (op9_language_model, "documents"),
    "op10_sentencepiece": (op10_sentencepiece, "documents"),
}


def queries() -> dict:
    def over(operator, table):
        return lambda spark, sf_dir: operator(spark.read.parquet(f"{sf_dir}/{table}.parquet"))

    return {name: over(*x) for name, x in _OPERATORS.items()}


def _preference_sql() -> str:
    middle, close = MIDDLE.replace("\n", "' || chr(10) || '"), CLOSE.replace("\n", "' || chr(10) || '")
    return f"""
WITH t AS (
  SELECT conv_id // 2 AS pair_id, conv_id % 2 AS side, turn, coalesce(role, 'user') AS role, coalesce(text, '') AS text
  FROM conversations WHERE conv_id IS NOT NULL),
n AS (SELECT *, row_number() OVER (PARTITION BY pair_id, side ORDER BY turn NULLS FIRST, role, text) AS k FROM t),
c AS (SELECT * FROM n WHERE side = 0), r AS (SELECT * FROM n WHERE side = 1),
j AS (
  SELECT coalesce(c.pair_id, r.pair_id) AS pair_id, coalesce(c.k, r.k) AS k,
         coalesce(c.role = r.role AND c.text = r.text, false) AS same
  FROM c FULL JOIN r ON c.pair_id = r.pair_id AND c.k = r.k),
p AS (SELECT pair_id, coalesce(min(k) FILTER (NOT same) - 1, max(k)) AS m FROM j GROUP BY pair_id),
x AS (
  SELECT p.pair_id, p.m, n.side, n.k, n.role, n.text,
         '{OPEN}' || n.role || '{middle}' || n.text || '{close}' AS line,
         length('{OPEN}' || n.role || '{middle}') AS head, n.k > p.m AND n.role = '{TRAINED_ROLE}' AS trained
  FROM p JOIN n USING (pair_id)),
y AS (SELECT *, coalesce(sum(length(line)) FILTER (k > m) OVER (PARTITION BY pair_id, side ORDER BY k ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) + head AS off FROM x)
SELECT pair_id, CAST(any_value(m) AS BIGINT) AS n_prompt_turns,
  coalesce(string_agg(line, '' ORDER BY k) FILTER (side = 0 AND k <= m), '') AS prompt,
  CASE WHEN count(*) FILTER (side = 0) > 0 THEN coalesce(string_agg(line, '' ORDER BY k) FILTER (side = 0 AND k > m), '') END AS chosen,
  CASE WHEN count(*) FILTER (side = 1) > 0 THEN coalesce(string_agg(line, '' ORDER BY k) FILTER (side = 1 AND k > m), '') END AS rejected,
  CASE WHEN count(*) FILTER (side = 0) > 0 THEN CAST(coalesce(sum(length(text) + {len(CLOSE)}) FILTER (side = 0 AND k > m AND role = '{TRAINED_ROLE}'), 0) AS BIGINT) END AS chosen_trained_chars,
  CASE WHEN count(*) FILTER (side = 1) > 0 THEN CAST(coalesce(sum(length(text) + {len(CLOSE)}) FILTER (side = 1 AND k > m AND role = '{TRAINED_ROLE}'), 0) AS BIGINT) END AS rejected_trained_chars,
  CASE WHEN count(*) FILTER (side = 0) > 0 THEN coalesce(string_agg(CAST(off AS BIGINT) || '-' || CAST(off + length(text) + {len(CLOSE)} AS BIGINT), ',' ORDER BY k) FILTER (side = 0 AND trained), '') END AS chosen_mask,
  CASE WHEN count(*) FILTER (side = 1) > 0 THEN coalesce(string_agg(CAST(off AS BIGINT) || '-' || CAST(off + length(text) + {len(CLOSE)} AS BIGINT), ',' ORDER BY k) FILTER (side = 1 AND trained), '') END AS rejected_mask
FROM y GROUP BY pair_id
"""


def _topk_sql() -> str:
    return f"""
WITH v AS (
  SELECT CAST(vec_id AS BIGINT) AS vec_id, list_transform(embedding, lambda x: CAST(floor({SCALE} * CAST(x AS DOUBLE)) AS BIGINT)) AS v
  FROM embeddings WHERE vec_id IS NOT NULL AND embedding IS NOT NULL
    AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
c AS (SELECT vec_id, unnest(v) AS x, generate_subscripts(v, 1) AS i FROM v),
s AS (
  SELECT q.vec_id AS query_id, c.vec_id, CAST(sum(q.x * c.x) AS BIGINT) AS score
  FROM c AS q JOIN c ON q.i = c.i AND q.vec_id <> c.vec_id WHERE q.vec_id % {STRIDE} = 0 GROUP BY 1, 2),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s)
SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score FROM r WHERE rank <= {K}
"""


def _quality_sql() -> str:
    def test(rule) -> str:
        base = f"CAST({rule.denominator} AS DOUBLE)" if rule.denominator else "1.0"
        sides = [f"{rule.numerator} >= {base} * CAST({rule.low} AS DOUBLE)"] if rule.low is not None else []
        sides += [f"{rule.numerator} <= {base} * CAST({rule.high} AS DOUBLE)"] if rule.high is not None else []
        return "(" + " AND ".join(sides) + ")"

    stops = ", ".join(f"'{w}'" for w in STOP_WORDS)
    names = ", ".join(f"CASE WHEN NOT {test(r)} THEN '{r.name}' END" for r in DEFAULT_RULES)
    base = f"(n_words < {MIN_WORDS} OR 100 * n_repeat_words > {MAX_REPEAT_PERCENT} * n_words)"
    return rf"""
WITH d AS (SELECT row_number() OVER () AS row, doc_id, coalesce(text, '') AS t FROM documents),
a AS (SELECT *, regexp_extract_all(t, '[^\x20\x09-\x0D]+') AS w,
        list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS l FROM d),
p AS (SELECT row, unnest(w) AS x, generate_subscripts(w, 1) AS i FROM a),
g AS (SELECT row, i, x AS a, lead(x) OVER o AS b, lead(x, 2) OVER o AS c FROM p WINDOW o AS (PARTITION BY row ORDER BY i)),
h AS (SELECT row, i, count(*) OVER (PARTITION BY row, a, b, c) AS n FROM g WHERE c IS NOT NULL),
k AS (SELECT row, count(DISTINCT i + s) AS n FROM h, (SELECT unnest([0, 1, 2]) AS s) WHERE h.n > 1 GROUP BY row),
m AS (SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words,
        CAST(length(regexp_replace(t, '[\x20\x09-\x0D]+', '', 'g')) AS BIGINT) AS word_chars,
        CAST(length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols,
        CAST(length(t) - length(replace(t, '!', '')) AS BIGINT) AS n_exclaims,
        len(list_filter(w, lambda x: x IN ({stops}))) AS n_stop_words,
        len(l) AS n_lines, CAST(len(l) - len(list_distinct(l)) AS BIGINT) AS n_dup_lines,
        len(list_filter(l, lambda x: rtrim(x, ' ') LIKE '%...')) AS n_ellipsis_lines,
        len(list_filter(l, lambda x: left(ltrim(x, ' '), 1) IN ('-', '*', '•'))) AS n_bullet_lines,
        CAST(coalesce(k.n, 0) AS BIGINT) AS n_repeat_words
      FROM a LEFT JOIN k USING (row))
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, {base} AS base_failed,
  NOT {base} AND {" AND ".join(test(r) for r in DEFAULT_RULES)} AS kept,
  array_to_string(list_filter([{names}], lambda x: x IS NOT NULL), ',') AS failed_rules
FROM m
"""


def oracle_sql() -> dict[str, str]:
    return {
        "op2_preference_format": _preference_sql(),
        "op4_exact_topk": _topk_sql(),
        "op8_quality_rules": _quality_sql(),
    }
