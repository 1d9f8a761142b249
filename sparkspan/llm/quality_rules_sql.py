"""DuckDB SQL for the quality rules' query."""

SQL = r"""
with d as (select doc_id, coalesce(text, '') as t from documents),
w as (select doc_id, t, regexp_extract_all(t, '[^\x20\x09-\x0D]+') as ws,
 list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) as ls from d),
grams as (select doc_id, i, array_to_string(ws[i:i+7], ' ') as g from w, unnest(range(1, greatest(len(ws) - 6, 1))) as r(i)),
rep as (select doc_id, i from (select doc_id, i, count(*) over (partition by doc_id, g) as n from grams) where n > 1),
cov as (select doc_id, sum(least(8, coalesce(nx - i, 8))) as n from (select doc_id, i, lead(i) over (partition by doc_id order by i) as nx from rep) group by doc_id),
c as (select w.doc_id, t, len(ws) as n_words, length(regexp_replace(t, '[\x20\x09-\x0D]', '', 'g')) as word_chars,
 length(t) - length(translate(t, '#*$%&|<>', '')) as n_symbols, len(ls) - len(list_distinct(ls)) as n_dup_lines, len(ls) as n_lines,
 coalesce(cov.n, 0) as n_repeat_words, length(regexp_replace(t, '\P{L}', '', 'g')) as letters, length(regexp_replace(t, '\P{Lu}', '', 'g')) as upper,
 length(t) - length(replace(t, '!', '')) as shouts from w left join cov using (doc_id)),
f as (select *, n_words < 20 or 100 * n_repeat_words > 30 * n_words as base_failed from c)
select doc_id, cast(n_words as bigint) as n_words, cast(word_chars as bigint) as word_chars, cast(n_symbols as bigint) as n_symbols,
 cast(n_dup_lines as bigint) as n_dup_lines, cast(n_repeat_words as bigint) as n_repeat_words, base_failed,
 not base_failed and not (10 * n_symbols > n_words or word_chars < 2 * n_words or word_chars > 12 * n_words or (n_dup_lines > 3 and 10 * n_dup_lines > 3 * n_lines)
 or 10 * upper > 5 * letters or 10 * letters < 5 * word_chars or 4 * shouts > n_words) as kept
from f
"""
