"""Pieces of DuckDB SQL that answer the text workloads independently of the Spark plans."""

from __future__ import annotations


def words(source: str = "documents", key: str = "doc_id", text: str = "text", letters: bool = True) -> str:
    """Common table expressions up to ``tok(doc_id, pos, word, begin, end)``; of blank-separated words without ``letters``."""
    other = "[^\\p{L}]+" if letters else "[\\x20\\x09-\\x0D]+"
    return f"""
d as (select {key} as doc_id, trim(regexp_replace(lower({text}), '{other}', ' ', 'g')) as c from {source}),
w as (select doc_id, string_split(c, ' ') as ws from d where c <> ''),
t as (select doc_id, unnest(ws) as word, (generate_subscripts(ws, 1) - 1)::bigint as pos from w),
o as (select doc_id, pos, word, coalesce(sum(length(word) + 1) over (partition by doc_id order by pos rows between unbounded preceding and 1 preceding), 0)::bigint as b from t),
tok as (select doc_id, pos, word, b as "begin", (b + length(word))::bigint as "end" from o)"""


def grams(n: int = 8, step: int = 1, order: bool = True, name: str = "g", **of: str) -> str:
    ws = ", ".join("word" if i == 0 else f"lead(word, {i}) over o" for i in range(n))
    g = f"concat_ws(' ', {ws})" if order else f"array_to_string(list_sort([{ws}]), ' ')"
    return f"""{words(**of)},
{name} as materialized (select * from (select doc_id, pos, "begin", lead("end", {n - 1}) over o as "end", {g} as g from tok window o as (partition by doc_id order by pos))
  where "end" is not null and pos % {step} = 0)"""


SEED_COLUMNS = """a.doc_id as a_doc, b.doc_id as b_doc, a.pos as a_pos, b.pos as b_pos,
  a."begin" as a_begin, a."end" as a_end, b."begin" as b_begin, b."end" as b_end"""


def seeds(n: int = 8, step: int = 1, order: bool = True, step_b: int | None = None, **of: str) -> str:
    other = "" if step_b in (None, step) else f",\ngb as (select * from g0 where pos % {step_b} = 0),\nga as (select * from g0 where pos % {step} = 0)"
    base = grams(n, step, order, **of) if not other else grams(n, 1, order, "g0", **of) + other
    a, b = ("ga", "gb") if other else ("g", "g")
    return f"{base},\ns as (select {SEED_COLUMNS} from {a} a join {b} b on a.g = b.g and a.doc_id < b.doc_id)"


def islands(source: str = "s", delta: int = 250, rounds: int = 2) -> str:
    """Groups of spans by gaps, along a and then b, ``rounds`` times; ends in ``k(a_doc, b_doc, a_begin, ...)``."""
    keys, parts, last = "a_doc, b_doc", [], source
    for r in range(rounds):
        for side in "ab":
            order = f"partition by {keys} order by {side}_begin, {side}_end"
            parts.append(f"x{r}{side} as (select *, case when {side}_begin - max({side}_end) over ({order} rows between unbounded preceding and 1 preceding) > {delta} then 1 else 0 end as gap from {last})")
            parts.append(f"y{r}{side} as (select * exclude (gap), sum(gap) over ({order} range unbounded preceding) as g{r}{side} from x{r}{side})")
            keys, last = f"{keys}, g{r}{side}", f"y{r}{side}"
    parts.append(f"k as (select a_doc, b_doc, min(a_begin) as a_begin, max(a_end) as a_end, min(b_begin) as b_begin, max(b_end) as b_end, count(*) as n_seeds from {last} group by {keys})")
    return ",\n".join(parts)


def cases(n: int = 8, step: int = 1, delta: int = 250, **of: str) -> str:
    return f"{seeds(n, step, **of)},\n{islands('s', delta)}"


CASE_COLUMNS = "a_doc, b_doc, a_begin, a_end, b_begin, b_end, n_seeds"


def signatures(n: int = 50, m: int = 10, **of: str) -> str:
    return f"""{words(**of)},
p as (select distinct doc_id, pos // {n} as passage_no, word from tok),
sig as (select doc_id, passage_no, i as slot, min(md5(i::varchar || ':' || word)) as hash from p cross join range({m}) r(i) group by 1, 2, 3)"""


def postings(n: int = 50, m: int = 10, keyed: bool = True) -> str:
    slot = "slot" if keyed else "0::bigint as slot"
    return f"{signatures(n, m)},\npost as (select distinct doc_id, {slot}, hash from sig)"


def candidates(n: int = 50, m: int = 10, keyed: bool = True, posts: str = "post", extra: str = "") -> str:
    return f"{postings(n, m, keyed)}{extra},\ncand as (select distinct a.doc_id as a_doc, b.doc_id as b_doc from {posts} a join {posts} b on a.slot = b.slot and a.hash = b.hash and a.doc_id < b.doc_id)"


FIELDS = """
dim as (select 'src' || i as field, 'area' || (i % 7) as area, 'disc' || ((i % 7) % 4) as discipline from range(20) r(i)
  union all select * from (values ('en', 'area0', 'disc0'), ('de', 'area1', 'disc1'), ('fr', 'area2', 'disc2'), ('es', 'area3', 'disc3')) v(field, area, discipline)),
pub0 as (select doc_id, length(text) as doc_chars, case when doc_id % 11 = 0 then null else 1860 + (doc_id * 37) % 159 end as pub_year, unnest([source, lang]) as field from documents),
pub as (select doc_id, any_value(doc_chars) as doc_chars, any_value(pub_year) as pub_year, string_agg(distinct p.field, '|' order by p.field) as fields,
  string_agg(distinct area, '|' order by area) as areas, string_agg(distinct discipline, '|' order by discipline) as disciplines
  from pub0 p left join dim on p.field = dim.field group by doc_id)"""


def draw(seed: str, *of: str) -> str:
    """A number from 0 to 2^32 - 1 by hash of texts."""
    return f"('0x' || substr(md5(concat_ws('|', '{seed}', {', '.join(of)})), 1, 8))::bigint"


def corpus(pairs: int = 10_000) -> str:
    """The labelled corpus: ``pair_id, strategy, a_text, b_text`` and the true spans, as one query."""
    clean = "string_split(trim(regexp_replace(lower(text), '[^\\p{L}]+', ' ', 'g')), ' ')"
    item = lambda name, step: f"join src {name} on {name}.k = (pr.p + {step}) % (select count(*) from src)"
    return f"""with dw as (select doc_id, {clean} as ws from documents), iw as (select item_id, {clean} as ws from benchmark),
gd as materialized (with {grams()} select doc_id, g from g), held as (select distinct doc_id from gd where g in (with {grams(source='benchmark', key='item_id')} select g from g)),
hosts as (select doc_id, ws, row_number() over (order by {draw('host', 'doc_id::varchar')}, doc_id) - 1 as n from dw where len(ws) >= 100 and doc_id not in (select doc_id from held)),
src as (select ws, row_number() over (order by {draw('n', 'item_id::varchar')}, item_id) - 1 as k from iw where len(ws) between 8 and 150),
pr0 as (select a.n // 2 as p, a.doc_id as ad, b.doc_id as bd, a.ws as ha, b.ws as hb from hosts a join hosts b on a.n % 2 = 0 and b.n = a.n + 1 where b.n < {2 * pairs}),
same as (select p from pr0 join gd x on x.doc_id = ad join gd y on y.doc_id = bd and y.g = x.g), pr as (select * from pr0 where p not in (select p from same)),
full_rows as (select pr.p, ha, hb, s.ws as s, f.ws[1:12] as formula, v.ws[1:5] as five, z.ws[1:7] as seven, ['verbatim', 'none', 'random', 'translation', 'summary'][pr.p % 5 + 1] as strategy
  from pr {item('s', 0)} {item('f', 1)} {item('v', 2)} {item('z', 3)}),
u as (select p, unnest(s) as w, generate_subscripts(s, 1) - 1 as i from full_rows),
x as (select *, {draw('s', 'p::varchar', '(i // 12)::varchar')} % 4 = 0 as intact from u),
y as (select *, case when intact then i else {draw('o', 'p::varchar', 'w', 'i::varchar')} end as o, case when intact then 9 else {draw('a', 'p::varchar', 'w', 'i::varchar')} % 10 end as act,
  case when not intact and {draw('v', 'w')} % 2 = 0 then reverse(w) else w end as f from x),
q as (select *, case when intact then f else coalesce(case when i % 2 = 0 then lead(f) over pw else lag(f) over pw end, f) end as t from y window pw as (partition by p order by i)),
obf as (select p, list(w order by i) as verbatim, flatten(list(case act when 0 then []::varchar[] when 1 then [reverse(w)] when 2 then [w, reverse(w)] else [w] end order by i // 4, o, w, i)) as random,
  list(t order by i) as translation, list(w order by i) filter ((i // 10) % 3 = 0) as summary from q group by p),
made as (select r.*, case strategy when 'verbatim' then verbatim when 'none' then []::varchar[] when 'random' then random when 'translation' then translation else summary end as put from full_rows r join obf using (p)),
parts as (select *, case when len(put) > 0 and (p // 5) % 4 = 0 then formula else []::varchar[] end as fo, ha[1:len(ha) // 2] as a1, ha[len(ha) // 2 + 1:] as a2, hb[1:len(hb) // 2] as b1, hb[len(hb) // 2 + 1:] as b2 from made),
texts as (select *, array_to_string(fo || five || a1, ' ') as ab, array_to_string(seven || b1, ' ') as bb from parts)
select p as pair_id, strategy, array_to_string(fo || five || a1 || put || a2 || seven, ' ') as a_text, array_to_string(seven || b1 || s || b2 || five || fo, ' ') as b_text,
  case when len(put) > 0 then length(ab) + 1 end as a_begin, case when len(put) > 0 then length(ab) + 1 + length(array_to_string(put, ' ')) end as a_end,
  case when len(put) > 0 then length(bb) + 1 end as b_begin, case when len(put) > 0 then length(bb) + 1 + length(array_to_string(s, ' ')) end as b_end from texts"""


CORPUS = f"corp as materialized ({corpus()}),\nsides as (select pair_id * 2 as doc_id, a_text as text from corp union all select pair_id * 2 + 1, b_text from corp)"


def detected(name: str, n: int = 8, step: int = 1, delta: int = 250, order: bool = True) -> str:
    """A table of the cases found in each pair of the corpus."""
    found = f"{grams(n, step, order, source='sides')},\ns as (select {SEED_COLUMNS} from g a join g b on a.g = b.g and a.doc_id % 2 = 0 and b.doc_id = a.doc_id + 1),\n{islands('s', delta)}"
    return f"{name} as materialized (with {found} select a_doc // 2 as pair_id, a_begin, a_end, b_begin, b_end, n_seeds from k)"


def counted(name: str) -> str:
    """Characters detected, true and both of each pair, one by one, for a table of cases."""
    chars = lambda t, more="": f"select pair_id, 'a' as side, unnest(range(a_begin, a_end)) as c from {t}{more} union select pair_id, 'b', unnest(range(b_begin, b_end)) from {t}{more}"
    return f"""fc as materialized ({chars(name)}), tc as materialized ({chars('corp', ' where a_begin is not null')}),
fn as (select pair_id, count(*) as detected from fc group by 1), tn as (select pair_id, count(*) as wanted from tc group by 1), bn as (select pair_id, count(*) as hits from fc semi join tc using (pair_id, side, c) group by 1),
n as (select pair_id, strategy, coalesce(hits, 0) as hits, coalesce(detected, 0) as detected, coalesce(wanted, 0) as wanted from corp left join fn using (pair_id) left join tn using (pair_id) left join bn using (pair_id))"""


def share(x: str, y: str, other: str) -> str:
    return f"case when {y} > 0 then {x} / {y} when {other} > 0 then 0.0::double else 1.0::double end"


MICRO = f"select strategy, {share('sum(hits)', 'sum(detected)', 'sum(wanted)')} as p, {share('sum(hits)', 'sum(wanted)', 'sum(detected)')} as r from n group by 1"
MACRO = f"select strategy, avg({share("hits", 'detected', 'wanted')}) as p, avg({share("hits", 'wanted', 'detected')}) as r from n group by 1"
F05 = "case when p + r > 0 then 1.25 * p * r / (0.25 * p + r) else 0.0::double end"
PRF = f"round(p, 6) as precision, round(r, 6) as recall, round({F05}, 6) as f05"
