"""Queries of the corpus operators and their DuckDB statements."""

from __future__ import annotations

from consensus_spark.llm import (
    lines,
    mixture,
    neighbours,
    ngram_trie,
    packing,
    rules,
    sharding,
    simhash,
    substrings,
    token_counts,
)

QUERIES = {
    "op1_quality_rules": rules.op1_quality_rules,
    "op2_shards": sharding.op2_shards,
    "op3_neighbours": neighbours.op3_neighbours,
    "op4_ngram_scores": ngram_trie.op4_ngram_scores,
    "op5_mixture": mixture.op5_mixture,
    "op6_substrings": substrings.op6_substrings,
    "op7_packing": packing.op7_packing,
    "op8_token_counts": token_counts.op8_token_counts,
    "op9_line_templates": lines.op9_line_templates,
    "op10_simhash": simhash.op10_simhash,
}

_STOP = ", ".join(f"'{w}'" for w in sorted({w for ws in rules.STOP_WORDS.values() for w in ws.split()}))
_PER = "CASE WHEN {b} > 0 THEN CAST({a} AS DOUBLE) / {b} ELSE 0.0::DOUBLE END"


def _per(a: str, b: str) -> str:
    return _PER.format(a=a, b=b)


def _verdict() -> str:
    tests = ["NOT base_failed"]
    for r in rules.RULES:
        tests += [f"{r.measure} >= {r.low}"] if r.low is not None else []
        tests += [f"{r.measure} <= {r.high}"] if r.high is not None else []
    return " AND ".join(tests)


_QUALITY = f"""WITH w AS (SELECT doc_id, coalesce(text, '') AS t, regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+') AS ws,
    list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: regexp_matches(x, '[^\\x20\\x09-\\x0D]')) AS ls FROM documents),
  win AS (SELECT doc_id, i, ws[i] || ' ' || ws[i + 1] || ' ' || ws[i + 2] AS g FROM w, range(1, len(ws) - 1) r(i)),
  rep AS (SELECT doc_id, i FROM win QUALIFY count(*) OVER (PARTITION BY doc_id, g) > 1),
  cov AS (SELECT doc_id, count(DISTINCT i + j) AS n FROM rep, range(3) s(j) GROUP BY doc_id),
  m AS (SELECT w.doc_id, ws, ls, CAST(len(ws) AS BIGINT) AS n_words, CAST(length(array_to_string(ws, '')) AS BIGINT) AS word_chars,
    CAST(length(regexp_replace(t, '[^#*$%&|<>]+', '', 'g')) AS BIGINT) AS n_symbols, CAST(len(ls) AS BIGINT) AS n_lines,
    CAST(len(ls) - len(list_distinct(ls)) AS BIGINT) AS n_dup_lines, CAST(coalesce(cov.n, 0) AS BIGINT) AS n_repeat_words,
    length(regexp_replace(t, '[^!?]+', '', 'g')) AS marks, length(regexp_replace(t, '[^\\p{{Lu}}]+', '', 'g')) AS up,
    length(regexp_replace(t, '[^\\p{{L}}]+', '', 'g')) AS letters FROM w LEFT JOIN cov USING (doc_id)),
  q AS (SELECT doc_id, n_words, word_chars, n_symbols, n_lines, n_dup_lines, n_repeat_words,
    {_per("word_chars", "n_words")} AS mean_word_chars, {_per("n_symbols", "n_words")} AS symbols_per_word,
    {_per("marks", "n_words")} AS marks_per_word, {_per("up", "letters")} AS upper_share,
    CAST(len(list_intersect([{_STOP}], list_transform(ws, lambda x: lower(x)))) AS BIGINT) AS distinct_stop_words,
    {_per("n_dup_lines", "n_lines")} AS duplicate_line_share,
    {_per("len(list_filter(ls, lambda x: regexp_matches(trim(x), '^[-*•]')))", "n_lines")} AS bullet_line_share,
    {_per("len(list_filter(ls, lambda x: regexp_matches(trim(x), '([.][.][.]|…)$')))", "n_lines")} AS ellipsis_line_share,
    n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM m)
  SELECT *, {_verdict()} AS kept FROM q"""

#: Hashes, token ids and searches of the other operators are beyond SQL; tests compare
#: them with brute force.
ORACLE_SQL: dict[str, str] = {"op1_quality_rules": _QUALITY}
