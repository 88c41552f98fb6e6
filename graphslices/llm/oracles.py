"""DuckDB SQL of the queries that SQL can express."""

from __future__ import annotations

from graphslices.llm import line_dedup, line_quality, url_templates
from graphslices.llm.queries import URL_RULES

WS = r"[\x20\x09-\x0D]"


def _line_fails(x: str, rules: line_quality.LineRules) -> str:
    """As line_quality.line_fails, over a column of lines."""
    words = f"len(list_filter(string_split_regex({x}, '{WS}+'), lambda w: w <> ''))"
    symbols = f"(length({x}) - length(regexp_replace({x}, '{line_quality.SYMBOLS}+', '', 'g')))"
    shouts = f"(len(string_split_regex({x}, '!!+')) - 1)"
    names, phrases = ("|".join(x).replace("'", "''") for x in (line_quality.NAVIGATION, line_quality.BOILERPLATE))
    return f"""(regexp_matches({x}, '[^\\x20\\x09-\\x0D]') and (
        {symbols} > {rules.symbol_share} * length({x}) or ({shouts} > 0 and {shouts} > {rules.shout_share} * {words})
        or (length({x}) >= {rules.sign_chars} and length({x}) - length(regexp_replace({x}, '{line_quality.UNLETTERED}', '', 'g')) > {rules.sign_share} * length({x}))
        or ({words} >= {rules.open_words} and not regexp_matches({x}, '[.!?;:…。！？؟।]'))
        or len(string_split_regex({x}, '\\s[|»·>]\\s')) - 1 >= {rules.bars}
        or (length({x}) <= {rules.short_chars} and (regexp_matches(lower({x}), '^\\W*(?:{names})\\W*$') or regexp_matches(lower({x}), '{phrases}')))))"""


def line_quality_sql(source: str = "documents", rules: line_quality.LineRules = line_quality.LineRules()) -> str:
    return f"""
with d as (select doc_id, coalesce(text, '') as t from {source}),
w as (select doc_id, t, list_filter(string_split_regex(t, '{WS}+'), lambda x: x <> '') as w from d),
five as (select doc_id, unnest(range(1, len(w) - 3)) as i, w from w where len(w) >= 5),
win as (select doc_id, i, array_to_string(w[i:i + 4], ' ') as g from five),
rep as (select doc_id, i from win qualify count(*) over (partition by doc_id, g) > 1),
covered as (select doc_id, count(distinct i + k) as n from rep, range(0, 5) r(k) group by doc_id),
l as (select doc_id, unnest(string_split(t, chr(10))) as x, generate_subscripts(string_split(t, chr(10)), 1) as i from d),
lines as (
  select doc_id, count(*) filter (regexp_matches(x, '[^\\x20\\x09-\\x0D]')) - count(distinct x) filter (regexp_matches(x, '[^\\x20\\x09-\\x0D]')) as dup,
    coalesce(sum(length(regexp_replace(x, '{WS}+', '', 'g'))) filter (not {_line_fails('x', rules)}), 0) as clean
  from l group by doc_id),
m as (
  select w.doc_id, len(w)::bigint as n_words, length(array_to_string(w, ''))::bigint as word_chars,
    (length(t) - length(regexp_replace(t, '{line_quality.SYMBOLS}+', '', 'g')))::bigint as n_symbols,
    dup::bigint as n_dup_lines, coalesce(covered.n, 0)::bigint as n_repeat_words, clean::bigint as clean_chars
  from w join lines using (doc_id) left join covered using (doc_id))
select *, n_words < {rules.min_words} or 100 * n_repeat_words > {rules.max_repeat_percent} * n_words as base_failed,
  not (n_words < {rules.min_words} or 100 * n_repeat_words > {rules.max_repeat_percent} * n_words) and clean_chars >= {1 - rules.lost_share} * word_chars as kept
from m"""


def line_dedup_sql(source: str = "documents", bound: line_dedup.LineBound = line_dedup.LineBound()) -> str:
    return f"""
with raw as (select doc_id, text, unnest(string_split(text, chr(10))) as x, generate_subscripts(string_split(text, chr(10)), 1) as i from {source} where text is not null),
l as (select doc_id, i, x, list_filter(string_split_regex(lower(x), '{WS}+'), lambda y: y <> '') as w from raw),
firsts as (select array_to_string(w, ' ') as k, min((doc_id, i)) as place, any_value(w) as w from l where len(w) > 0 group by 1),
v as (select place, w, unnest(range(1, len(w) + 1)) as j from firsts where len(w) >= {bound.min_words}),
cuts as (select place, j, len(w) as n, array_to_string(w[1:j - 1] || w[j + 1:], ' ') as k from v),
near as (
  select place from cuts qualify min(place) over (partition by n, j, k) < place
  union select c.place from cuts c join firsts f on c.k = f.k and len(f.w) >= {bound.min_words} where f.place < c.place
  union select f.place from cuts c join firsts f on c.k = f.k and len(f.w) >= {bound.min_words} where c.place < f.place),
stay as (select place from firsts where place not in (select place from near)),
marked as (select doc_id, i, x, len(w) > 0 as spoken, len(w) = 0 or (doc_id, i) in (select place from stay) as kept from l)
select d.doc_id, string_agg(x, chr(10) order by i) filter (kept) as text0, count(i) filter (spoken) as n_lines, count(i) filter (spoken and kept) as n_kept,
  case when d.text is null then null else coalesce(text0, '') end as text
from {source} d left join marked m on m.doc_id = d.doc_id group by d.doc_id, d.text"""


def url_templates_sql(rules: list[url_templates.Rule], limits: url_templates.TreeLimits = url_templates.TreeLimits()) -> str:
    """The tree level by level: one statement for each, as deep as the limits say."""
    t = limits
    order = sorted(rules, key=lambda r: (-len(r.text), r.text))
    fits = {r: f"((host = '{r.host}' or ends_with(host, '.{r.host}')) and starts_with(path, '{r.path}'))" for r in order}
    levels = []
    for k in range(1, t.max_depth + 1):
        levels.append(f"""
k{k} as (select host, template, seg[{k + 1}] as child, sum(n) as n, sum(labelled) as labelled, sum(bad) as bad from t{k - 1} where seg[{k + 1}] is not null group by all),
n{k} as (select host, template, count(*) as fan, sum(n) as an, sum(labelled) as al, sum(bad) as ab from k{k} group by all),
m{k} as (select host, template, child, case when child = '' then '' when fan = 1 then child when fan > {t.max_children} and n < {t.rare_share} * an then '*'
    when labelled > 0 and abs(bad / labelled - ab / al) > {t.z} * sqrt(ab / al * (1 - ab / al) / labelled) then child else '*' end as name from k{k} join n{k} using (host, template)),
t{k} as materialized (select t.host, shape, case when m.child is null then t.template else t.template || '/' || m.name end as template, n, labelled, bad, seg
    from t{k - 1} t left join m{k} m on t.host = m.host and t.template = m.template and t.seg[{k + 1}] = m.child)""")
    d = t.max_depth
    return f"""
with u as (select page_id, case when instr(url, '://') > 0 then substr(url, instr(url, '://') + 3) else '' end as rest from pages),
h as (select page_id, coalesce(rest, '') as rest, regexp_extract(coalesce(rest, ''), '^[^/?#]*') as raw from u),
p as (select page_id, translate(raw, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as host, regexp_extract(substr(rest, length(raw) + 1), '^[^?#]*') as path from h),
s as (select *, regexp_replace(lower(path), '[0-9]+', '{{n}}', 'g') as shape from p),
l as (select doc_id as page_id, count(*) as labelled, sum(greatest(1 - quality, toxic)) as bad from labels where quality is not null or toxic is not null group by 1),
t0 as materialized (select host, shape, '' as template, count(*) as n, coalesce(sum(labelled), 0) as labelled, coalesce(sum(bad), 0) as bad, string_split(shape, '/') as seg from s left join l using (page_id) group by host, shape),
{','.join(levels)},
tree as (select host, shape, template || case when len(seg) > {d + 1} then '/' || array_to_string(seg[{d + 2}:], '/') else '' end as template, labelled, bad from t{d}),
hosts as (select host, sum(labelled) as hl, sum(bad) as hb from tree group by host),
g as (select (sum(hl - hb) + 1) / (sum(hl) + 2) as g from hosts),
leaves as (select host, template, sum(labelled) as l, ((sum(labelled) - sum(bad)) + {t.prior} * ((any_value(hl) - any_value(hb)) + {t.prior} * any_value(g)) / (any_value(hl) + {t.prior})) / (sum(labelled) + {t.prior}) as purity
    from tree join hosts using (host), g group by host, template)
select page_id, s.host, path, case {' '.join(f"when {fits[r].replace('host', 's.host')} then '{r.text}'" for r in order)} end as rule,
  case {' '.join(f"when {fits[r].replace('host', 's.host')} then '{r.verdict}'" for r in order)} when l > 0 and purity < {t.min_purity} then 'block' else 'allow' end as verdict, template, purity
from (select page_id, host, path, shape from s) s join tree using (host, shape) join leaves using (host, template)"""


ORACLES = {
    "op1_url_templates": url_templates_sql(URL_RULES),
    "op8_line_dedup": f"select doc_id, text, n_lines, n_kept from ({line_dedup_sql()})",
    "op9_line_quality": line_quality_sql(),
}
