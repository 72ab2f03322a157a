"""DuckDB SQL of the queries that SQL can express."""

from . import licenses, quality_rules, url_filters

_HOST_RULES = ", ".join(f"('{r.pattern}', '{r.verdict}', '{url_filters.regex(r)}')" for r in url_filters.HOST_RULES)
_PATTERNS = ", ".join(f"('{r.pattern}', '{r.verdict}', '{url_filters.regex(r)}')" for r in url_filters.PATTERN_RULES)

_URL_FILTERS = rf"""
with parts as (
  select page_id,
         case when instr(url, '://') > 0 then translate(regexp_extract(substr(url, instr(url, '://') + 3), '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') else '' end as host,
         case when instr(url, '://') > 0 then regexp_extract(substr(url, instr(url, '://') + 3), '^[^/?#]*([^?#]*)', 1) else '' end as path
  from pages),
fixed(rule, verdict, regex) as (values {_HOST_RULES}),
own(rule, verdict, regex) as (values {_PATTERNS}),
places as (select distinct host || path as place from parts),
hit as (
  select place,
         (select rule from fixed where regexp_matches(place, regex) order by length(rule) desc, rule limit 1) as rule,
         (select rule from own where regexp_matches(place, regex) order by length(rule) desc, rule limit 1) as pattern
  from places)
select page_id, host, path, hit.rule as rule, hit.pattern as pattern, coalesce(fixed.verdict, own.verdict, 'allow') as verdict
from parts
join hit on hit.place = host || path
left join fixed on fixed.rule = hit.rule
left join own on own.rule = hit.pattern
"""

_TEMPLATES = ", ".join("('%s', '%s')" % (name, text.replace("'", "''")) for name, text in licenses.TEMPLATES)
_TERMS = f"unnest(regexp_extract_all(lower({{}}), '{licenses.TERM}')) as term"

_LICENSES = rf"""
with t(license, template) as (values {_TEMPLATES}),
f as (select row_number() over () as row, doc_id, source || '/' || lang || '/' || doc_id as path, source || '/' || lang as dir, source as top, text from documents),
lines as (select row, trim(line) as unit from (select row, unnest(string_split(text, chr(10))) as line from f) where regexp_matches(trim(line), '{licenses.TRIGGER}')),
spoken as (select row, sum(length(unit)) as spoken from lines group by row),
held as (select distinct row, unit from lines),
units as (select unit, count(*) as n from held group by unit),
total as (select coalesce(sum(n), 0) as total from units),
tf as (select unit, n, term, count(*) as tf from (select unit, n, {_TERMS.format('unit')} from units) group by all),
df as (select term, sum(n) as df from tf group by term),
base as (select license, template, term, count(*) * (ln((1.0 + any_value(total)) / (1.0 + coalesce(any_value(df), 0))) + 1.0) as w
  from (select license, template, {_TERMS.format('template')} from t) left join df using (term), total group by license, template, term),
base_norm as (select license, template, sqrt(sum(w * w)) as norm from base group by all),
weighed as (select unit, term, tf * (ln((1.0 + total) / (1.0 + df)) + 1.0) as w from tf join df using (term), total),
norms as (select unit, sqrt(sum(w * w)) as norm from weighed group by unit),
dots as (select unit, b.license, b.template, sum(x.w * b.w / m.norm) as dot from weighed x join base b using (term) join base_norm m on m.license = b.license and m.template = b.template group by all),
scored as (select unit, license, round(dot / norm, 4) as score from dots join norms using (unit)),
best as (select unit, license, score from (select *, row_number() over (partition by unit order by score desc, license) as k from scored) where k = 1 and score >= {licenses.MIN_COSINE}),
own as (select row, license, score from (select row, license, score, row_number() over (partition by row order by score desc, license) as k from held join best using (unit)) where k = 1),
files as (select f.*, own.license, own.score, coalesce(spoken >= {licenses.FILE_SHARE} * length(text) and spoken > 0, false) as is_file from f left join own using (row) left join spoken using (row)),
sources as (select dir as above, license as above_license, score as above_score from (select dir, license, score, row_number() over (partition by dir order by score desc, license, path) as k from files where is_file and license is not null) where k = 1),
ancestors as (select distinct dir, unnest(['', top, dir]) as above from f),
nearest as (select dir, above, above_license, above_score from (select a.dir, s.*, row_number() over (partition by a.dir order by length(s.above) desc) as k from ancestors a join sources s using (above)) where k = 1)
select doc_id, path, coalesce(license, above_license) as license, coalesce(score, above_score) as score,
 case when license is not null then 'header' when above_license is not null then 'inherited' else 'none' end as how,
 case when license is null then above end as inherited_from
from files left join nearest using (dir)
"""

_LIMITS = quality_rules.Limits()
_SPACE = "' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)"
_LENGTHS = sorted(_LIMITS.ngram_chars)


def _gram(n: int) -> str:
    """Share of word characters inside n-grams found again, by document."""
    leads = ", ".join(["w"] + [f"lead(w, {k}) over o as w{k}" for k in range(1, n)])
    key = ", ".join(["w"] + [f"w{k}" for k in range(1, n)])
    return f"""a{n} as (select row, i, size, n, {leads} from words window o as (partition by row order by i)),
b{n} as (select row, i, size, i <= n - {n - 1} and count(*) over (partition by row, i <= n - {n - 1}, {key}) > 1 as again from a{n}),
c{n} as (select row, size, bool_or(again) over (partition by row order by i rows between {n - 1} preceding and current row) as hit from b{n}),
g{n} as (select row, sum(case when hit then size else 0 end)::double / sum(size)::double as share from c{n} group by row)"""


_RULES = rf"""
with f as (select row_number() over () as row, doc_id, coalesce(text, '') as text from documents),
split as (select row, regexp_extract_all(text, '[^\x20\x09-\x0D]+') as l from f),
words as (select row, unnest(l) as w, unnest(range(1, len(l) + 1)) as i, len(l) as n, length(unnest(l)) as size from split),
w3 as (select row, i, n, w, lead(w) over o as w1, lead(w, 2) over o as w2 from words window o as (partition by row order by i)),
d3 as (select row, i, i <= n - 2 and count(*) over (partition by row, i <= n - 2, w, w1, w2) > 1 as again from w3),
r3 as (select row, sum(case when hit then 1 else 0 end) as n_repeat_words from (select row, bool_or(again) over (partition by row order by i rows between 2 preceding and current row) as hit from d3) group by row),
{", ".join(_gram(n) for n in _LENGTHS)},
counted as (select row, count(*) as n_words, sum(length(w)) as word_chars from words group by row),
cut as (select row, string_split(text, chr(10)) as l from f),
lines as (select row, line, length(trim(line, {_SPACE})) as size, row_number() over (partition by row, line order by i) as k from (select row, unnest(l) as line, unnest(range(1, len(l) + 1)) as i from cut) where length(trim(line, {_SPACE})) > 0),
dup as (select row, sum(case when k > 1 then 1 else 0 end) as n_dup_lines, sum(case when k > 1 then size else 0 end)::double / sum(size)::double as dup_line_chars from lines group by row),
m as (
  select doc_id, coalesce(n_words, 0) as n_words, coalesce(word_chars, 0) as word_chars, length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')) as n_symbols,
    coalesce(n_dup_lines, 0) as n_dup_lines, coalesce(n_repeat_words, 0) as n_repeat_words, coalesce(dup_line_chars, 0.0) as dup_line_chars,
    coalesce(greatest({", ".join(f"g{n}.share" for n in _LENGTHS)}), 0.0) as dup_ngram_chars
  from f left join counted using (row) left join r3 using (row) left join dup using (row) {" ".join(f"left join g{n} using (row)" for n in _LENGTHS)})
select doc_id, cast(n_words as bigint) as n_words, cast(word_chars as bigint) as word_chars, cast(n_symbols as bigint) as n_symbols, cast(n_dup_lines as bigint) as n_dup_lines, cast(n_repeat_words as bigint) as n_repeat_words,
  dup_line_chars, dup_ngram_chars, failed as base_failed,
  not failed and dup_line_chars <= {_LIMITS.line_chars!r} and n_symbols <= {_LIMITS.symbols_per_word!r} * n_words and dup_ngram_chars <= {max(_LIMITS.ngram_chars.values())!r} as kept
from (select *, n_words < {_LIMITS.min_words} or 100 * n_repeat_words > {_LIMITS.repeat_words_percent} * n_words as failed from m)
"""

ORACLES = {"op2_url_filters": _URL_FILTERS, "op5_license_scan": _LICENSES, "op7_quality_rules": _RULES}
