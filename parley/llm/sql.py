"""DuckDB SQL for the text operators that SQL can express, over whole tables."""

QUALITY_MEASURES = r"""
WITH t AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
w AS (SELECT doc_id, text, regexp_extract_all(text, '[^\x20\x09-\x0D]+') AS words,
             list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS lines FROM t),
win AS (SELECT doc_id, unnest(range(1, len(words) - 6)) AS pos, words FROM w WHERE len(words) >= 8),
keyed AS (SELECT doc_id, pos, array_to_string(words[pos:pos + 7], ' ') AS k FROM win),
twice AS (SELECT doc_id, pos FROM (SELECT *, count(*) OVER (PARTITION BY doc_id, k) AS n FROM keyed) WHERE n > 1),
gaps AS (SELECT doc_id, least(8, coalesce(pos - lag(pos) OVER (PARTITION BY doc_id ORDER BY pos), 8)) AS g FROM twice),
rep AS (SELECT doc_id, sum(g) AS n_repeat_words FROM gaps GROUP BY doc_id),
m AS (SELECT w.doc_id, len(words)::BIGINT AS n_words, length(array_to_string(words, ''))::BIGINT AS word_chars,
             length(regexp_replace(text, '[^#*$%&|<>]+', '', 'g'))::BIGINT AS n_symbols, len(lines)::BIGINT AS n_lines,
             (len(lines) - len(list_distinct(lines)))::BIGINT AS n_dup_lines, coalesce(n_repeat_words, 0)::BIGINT AS n_repeat_words
      FROM w LEFT JOIN rep USING (doc_id)),
b AS (SELECT *, (CASE WHEN n_words < 20 THEN 1 ELSE 0 END + CASE WHEN 100 * n_repeat_words > 30 * n_words THEN 2 ELSE 0 END
             + CASE WHEN 4 * n_symbols > n_words THEN 4 ELSE 0 END + CASE WHEN 2 * n_dup_lines > n_lines THEN 8 ELSE 0 END
             + CASE WHEN word_chars < 2 * n_words THEN 16 ELSE 0 END + CASE WHEN word_chars > 20 * n_words THEN 32 ELSE 0 END)::BIGINT AS fail_bits FROM m)
"""

QUALITY = QUALITY_MEASURES + """
SELECT doc_id, n_words, word_chars, n_symbols, n_lines, n_dup_lines, n_repeat_words, fail_bits,
       fail_bits & 3 != 0 AS base_failed, fail_bits = 0 AS kept FROM b
"""

#: The rules of policy v2 and their bits.
ABLATION = QUALITY_MEASURES + """
, r AS (SELECT * FROM (VALUES ('few_words', 1), ('repeated_windows', 2), ('symbols', 4), ('repeated_lines', 8), ('tiny_words', 16), ('giant_words', 32)) v(rule, bit)),
c AS (SELECT fail_bits AS bits, count(*) AS n FROM b GROUP BY 1)
SELECT rule, coalesce(sum(n) FILTER (bits & bit != 0), 0)::BIGINT AS n_failed, coalesce(sum(n) FILTER (bits = bit), 0)::BIGINT AS n_only_this,
       bit_or(bits) FILTER (bits & bit != 0)::BIGINT AS fails_with FROM c, r GROUP BY rule
"""
