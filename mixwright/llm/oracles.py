"""DuckDB SQL for the operators that SQL can express."""

from __future__ import annotations

from . import quality_rules


def _literal(words) -> str:
    return "[" + ", ".join("'" + w.replace("'", "''") + "'" for w in words) + "]"


def quality_rules_sql() -> str:
    rules = quality_rules.default_rules()
    bounds = [f"{r.measure} >= {r.low}" for r in rules.rules if r.low is not None] + [f"{r.measure} <= {r.high}" for r in rules.rules if r.high is not None]
    per = lambda a, b: f"CASE WHEN {b} > 0 THEN {a}::DOUBLE / {b} ELSE 0.0 END"
    return rf"""
    WITH base AS (
      SELECT doc_id, coalesce(text, '') AS t,
        list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS words,
        list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS lines
      FROM documents
    ), word AS (
      SELECT doc_id, unnest(words) AS w, generate_subscripts(words, 1) AS pos, len(words) AS n FROM base
    ), gram AS (
      SELECT doc_id, pos, CASE WHEN pos <= n - 7 THEN [w, {', '.join(f'lead(w, {i}) OVER o' for i in range(1, 8))}] END AS g
      FROM word WINDOW o AS (PARTITION BY doc_id ORDER BY pos)
    ), twin AS (
      SELECT doc_id, pos, g IS NOT NULL AND count(*) OVER (PARTITION BY doc_id, g) > 1 AS hit FROM gram
    ), cover AS (
      SELECT doc_id, max(hit::INT) OVER (PARTITION BY doc_id ORDER BY pos ROWS BETWEEN 7 PRECEDING AND CURRENT ROW) AS c FROM twin
    ), rep AS (
      SELECT doc_id, sum(c)::BIGINT AS n_repeat_words FROM cover GROUP BY doc_id
    ), counts AS (
      SELECT b.doc_id, len(words)::BIGINT AS n_words, length(array_to_string(words, ''))::BIGINT AS word_chars,
        (length(t) - length(regexp_replace(t, '{quality_rules.SYMBOLS}', '', 'g')))::BIGINT AS n_symbols,
        (len(lines) - len(list_distinct(lines)))::BIGINT AS n_dup_lines,
        coalesce(n_repeat_words, 0)::BIGINT AS n_repeat_words,
        length(t) - length(replace(t, '!', '')) AS n_bangs,
        length(regexp_replace(t, '\P{{Lu}}+', '', 'g')) AS n_upper,
        len(list_filter(words, lambda w: list_contains({_literal(rules.stop_words)}, lower(w)))) AS n_stops,
        len(lines) AS n_lines,
        len(list_filter(lines, lambda x: regexp_matches(x, '^[ \t\n\v\f\r]*[-*•‣]'))) AS n_bullets,
        len(list_filter(lines, lambda x: regexp_matches(x, '(\.\.\.|…)[ \t\n\v\f\r]*$'))) AS n_dots
      FROM base b LEFT JOIN rep USING (doc_id)
    ), ratios AS (
      SELECT *, {per('word_chars', 'n_words')} AS mean_word_chars, {per('n_symbols', 'n_words')} AS symbols_per_word,
        {per('n_bangs', 'n_words')} AS bangs_per_word, {per('n_upper', 'word_chars')} AS upper_share, {per('n_stops', 'n_words')} AS stop_share,
        {per('n_repeat_words', 'n_words')} AS repeat_share, {per('n_dup_lines', 'n_lines')} AS dup_line_share,
        {per('n_bullets', 'n_lines')} AS bullet_line_share, {per('n_dots', 'n_lines')} AS ellipsis_line_share,
        (n_words < 20 OR 100 * n_repeat_words > 30 * n_words) AS base_failed
      FROM counts
    )
    SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, (NOT base_failed AND {' AND '.join(bounds)}) AS kept FROM ratios
    """


def reply_trees_sql() -> str:
    control = r"'([<\[])(\\*)(/?(?:s>|INST\]))', '\1\\\2\3', 'g'"
    return rf"""
    WITH rows AS (
      SELECT conv_id, turn, role, text FROM conversations
      UNION ALL SELECT -1, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -1, 1, 'assistant', '</s>[INST] ok [/INST]'
    ), t AS (
      SELECT conv_id, row_number() OVER (PARTITION BY conv_id ORDER BY turn, role, text) AS n, coalesce(role, '') AS role, coalesce(text, '') AS text FROM rows
    ), c AS (
      SELECT conv_id, count(*)::BIGINT AS n_turns, string_agg(role || chr(10) || text || chr(10), '' ORDER BY n) AS whole,
        coalesce(string_agg(text, '' ORDER BY n) FILTER (role = 'assistant'), '') AS learnt,
        sum({len("<s>[INST]") + len("[/INST]") + len("</s>")} + length(regexp_replace(role, {control})) + length(regexp_replace(text, {control})))::BIGINT AS formatted_chars
      FROM t GROUP BY conv_id
    )
    SELECT conv_id, n_turns, sha256(whole) AS turns_sha256, length(learnt)::BIGINT AS loss_chars, sha256(learnt) AS loss_sha256, formatted_chars FROM c
    """
