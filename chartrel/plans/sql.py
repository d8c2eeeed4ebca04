"""DuckDB SQL of the registered queries, written from the definitions and not from the Spark plans."""

from __future__ import annotations

from ..functions.color import HSV_SQL
from ..functions.draws import draw_sql
from ..operators.synth import RGB3, STYLES, TYPES, WIDE
from ..operators.truth import relations_sql
from ..sources.families import POINTS_SQL

_KEY = "concat_ws('|', chart_id, series_key)"
SUP = POINTS_SQL["supplier"]
CUST3 = POINTS_SQL["customer_status"]


def colours(points: str, pool=RGB3) -> str:
    at = f"[{', '.join('[' + ', '.join(map(str, c)) + ']' for c in pool)}][((series_no - 1) % {len(pool)}) + 1]"
    return f"select chart_id, series_key, series_no, {at}[1] as r, {at}[2] as g, {at}[3] as b from (select chart_id, series_key, dense_rank() over (partition by chart_id order by series_key)::int as series_no from (select distinct chart_id, series_key from ({points})))"


def placed(points: str, pool=RGB3) -> str:
    return f"""select chart_id, series_no, x, y,
      (case when x1 = x0 then 80 else 20 + ((x - x0) * 119) // (x1 - x0) end)::int as px,
      (case when y1 = y0 then 59 else 103 - ((y - y0) * 89) // (y1 - y0) end)::int as py
      from (select p.chart_id, c.series_no, x, y, min(x) over (partition by p.chart_id) as x0, max(x) over (partition by p.chart_id) as x1, min(y) over (partition by p.chart_id) as y0, max(y) over (partition by p.chart_id) as y1
            from ({points}) p join ({colours(points, pool)}) c using (chart_id, series_key))"""


def drawn_colours(points: str) -> str:
    """Colours that each series draws from the wide pool."""
    at = f"[{', '.join('[' + ', '.join(map(str, c)) + ']' for c in WIDE)}][({draw_sql(_KEY, 'colour')} % {len(WIDE)}) + 1]"
    return f"select chart_id, series_key, series_no, {at}[1] as r, {at}[2] as g, {at}[3] as b from ({colours(points)})"


def marks(kind: str, points: str = SUP, pool=RGB3) -> str:
    base = placed(points, pool)
    if kind == "scatter":
        return f"select distinct chart_id, series_no, px + dx as px, py + dy as py from ({base}), (values (-1), (0), (1)) a(dx), (values (-1), (0), (1)) b(dy)"
    if kind == "line":
        return f"""select distinct chart_id, series_no, cx as px, unnest(range(least(f, t), greatest(f, t) + 1)) as py from (
          select chart_id, series_no, cx,
            case when qx = px then py else py + ((qy - py) * (cx - px)) // (qx - px) end as f,
            case when qx = px then qy else py + ((qy - py) * least(cx - px + 1, qx - px)) // (qx - px) end as t
          from (select *, unnest(range(px, qx + 1)) as cx from (
            select chart_id, series_no, px, py, coalesce(lead(px) over w, px) as qx, coalesce(lead(py) over w, py) as qy from ({base}) window w as (partition by chart_id, series_no order by x, y))))"""
    return f"""select distinct chart_id, series_no, px, unnest(range(py, 104)) as py from (
      select chart_id, series_no, py, unnest(range(spot, spot + greatest(0, wide - 2) + 1)) as px from (
        select chart_id, series_no, spot, wide, min(py) as py from (
          select chart_id, series_no, py, wide, 20 + (slot * 120) // slots + (series_no - 1) * wide as spot from (
            select *, greatest(1, 120 // (slots * many)) as wide from (
              select p.*, dense_rank() over (partition by chart_id order by x) - 1 as slot, s.slots, s.many from ({base}) p
              join (select chart_id, count(distinct x) as slots, max(series_no) as many from ({base}) group by 1) s using (chart_id))))
        group by 1, 2, 3, 4))"""


def painted(kind: str, points: str = SUP, pool=RGB3) -> str:
    return f"select chart_id, px::int as px, py::int as py, series_no, r, g, b from (select chart_id, px, py, max(series_no) as series_no from ({marks(kind, points, pool)}) group by 1, 2, 3) join ({colours(points, pool)}) c using (chart_id, series_no)"


def ink(kind: str) -> str:
    return painted(kind)


def degraded(px: str) -> str:
    u = draw_sql("concat_ws(',', chart_id, px, py)", "speckle")
    return f"""with px as materialized (select chart_id, px, py, r, g, b from ({px})),
      spots as (select distinct chart_id, (px + u % 7 - 3)::int as px, (py + u % 11 - 5)::int as py from (select *, {u} as u from px) where u % 60 = 0)
      select * from px union all select s.chart_id, s.px, s.py, 190, 184, 196 from spots s anti join px using (chart_id, px, py)"""


def hsv(px: str, more: str = "chart_id") -> str:
    return f"select {more}, r, g, b, {HSV_SQL} from (select {more}, r::bigint as r, g::bigint as g, b::bigint as b from ({px}))"


def saturate(px: str, background: int = 255, more: str = "chart_id") -> str:
    up, k = "((h % 30) * 255 + 15) // 30", "h // 30 + 1"
    pick = lambda *c: f"(case when s > 64 then [{', '.join(c)}][{k}] else {background} end)::int"
    u, dn = f"({up})", f"(255 - ({up}))"
    return f"select {more}, {pick('255', dn, '0', '0', u, '255')} as r, {pick(u, '255', '255', dn, '0', '0')} as g, {pick('0', '0', u, '255', '255', dn)} as b from ({hsv(px, more)})"


def saturated(background: str) -> str:
    return f"select chart_id, r, g, b, count(*) as n from ({saturate(degraded(painted('scatter', SUP, WIDE)), 255 if background == 'white' else 0)}) group by all"


def histogram(px: str) -> str:
    return f"""with h as (select chart_id, r, g, b, count(*) as w from ({px}) group by all)
      select chart_id, r, g, b, sum(w)::bigint as w from (select * from h union all select chart_id, 255, 255, 255, 19200 - sum(w) from h group by 1) group by all"""


def clean_centers(kind: str = "line") -> str:
    return f"""select chart_id, (n - 1)::int as series_no, r, g, b, w from (
      select *, row_number() over (partition by chart_id order by w desc, r, g, b) as n from ({histogram(saturate(painted(kind)))}) where w > 0) where n > 1"""


def ranges(s: int = 25, literal: bool = False, of: str = "") -> str:
    of = of or f"select vec_id as chart_id, 1 as series_no, r, g, b from ({EMBEDDING_COLOURS})"
    lo = (lambda c, d: f"least(0, {c} - {d})") if literal else (lambda c, d: f"greatest(0, {c} - {d})")
    hi = (lambda c, d, t: f"greatest({t}, {c} + {d})") if literal else (lambda c, d, t: f"least({t}, {c} + {d})")
    rest = f"{lo('s', s)}::int as slo, {hi('s', s, 255)}::int as shi, {lo('v', 40)}::int as vlo, {hi('v', 40, 255)}::int as vhi"
    return f"""with c as ({hsv(of, 'chart_id, series_no')})
      select chart_id, series_no, 1 as part, {lo('h', 10)}::int as hlo, {hi('h', 10, 180)}::int as hhi, {rest} from c
      union all select chart_id, series_no, 2, (case when h < 10 then h + 170 else 0 end)::int, (case when h < 10 then 180 else h - 170 end)::int, {rest} from c where h < 10 or h > 170"""


def masks(kind: str = "line") -> str:
    return f"""select distinct chart_id, series_no, px, py from ({hsv(saturate(painted(kind), 255, 'chart_id, px, py'), 'chart_id, px, py')}) p
      join ({ranges(of=f"select chart_id, series_no, r, g, b from ({clean_centers(kind)})")}) b using (chart_id)
      where h between hlo and hhi and s between slo and shi and v between vlo and vhi"""


def programmed() -> str:
    cols = f"select chart_id, series_no::varchar as series_key, px::bigint as x, (-floor(sum(py) * 1000 / count(*)))::bigint as y from ({masks()}) group by chart_id, series_no, px"
    return f"select chart_id, series_no, r, g, b, relation from ({clean_centers()}) join (select chart_id, series_key::int as series_no, relation from ({relations_sql(cols)})) using (chart_id, series_no)"


def true_series(points: str = SUP) -> str:
    return f"select * from ({relations_sql(points)}) join ({colours(points)}) using (chart_id, series_key)"


def near_cut(points: str) -> str:
    """Series whose |rho| lies from 1/4 to 11/20."""
    return f"""with p as ({points}),
      r as (select chart_id, series_key, (2 * rank() over (partition by chart_id, series_key order by x) + count(*) over (partition by chart_id, series_key, x) - 1)::hugeint as a,
        (2 * rank() over (partition by chart_id, series_key order by y) + count(*) over (partition by chart_id, series_key, y) - 1)::hugeint as b from p),
      s as (select chart_id, series_key, count(*) * sum(a * b) - sum(a) * sum(b) as num, (count(*) * sum(a * a) - sum(a) * sum(a)) * (count(*) * sum(b * b) - sum(b) * sum(b)) as den from r group by 1, 2)
      select chart_id, series_key from s where den > 0 and 16 * num * num >= den and 400 * num * num <= 121 * den"""


def right(pred: str, true: str) -> str:
    return f"""select distinct t.chart_id, t.series_key from ({hsv(true, 'chart_id, series_key, relation')}) t join ({hsv(pred, 'chart_id, relation')}) p on t.chart_id = p.chart_id and t.relation = p.relation
      where least(abs(t.h - p.h), 180 - abs(t.h - p.h)) <= 10"""


def per_chart(pred: str, true: str) -> str:
    return f"select chart_id, avg(case when ok is null then 0.0 else 1.0 end) as share from (select chart_id, series_key from ({true}) where relation <> 'undefined') left join (select *, 1 as ok from ({right(pred, true)})) using (chart_id, series_key) group by 1"


def score(what: str) -> str:
    pred, true = "select * from pred", "select * from tru"
    head = f"with pred as materialized ({programmed()}), tru as materialized ({true_series()}) "
    if what == "no_ocr":
        return head + f"select 'series_no_ocr' as metric, count(*) as n, round(avg(share), 6) as value from ({per_chart(pred, true)})"
    if what == "boundary":
        kept = f"select t.* from tru t anti join ({near_cut(SUP)}) using (chart_id, series_key)"
        return head + f"select 'series_no_ocr' as metric, count(*) as n, round(avg(share), 6) as value from ({per_chart(pred, kept)})"
    if what == "raw":
        c = lambda t, p: f"select chart_id, count(*) filter (relation = 'increasing') as {p}i, count(*) filter (relation = 'decreasing') as {p}d, count(*) filter (relation = 'neutral') as {p}n from ({t}) group by 1"
        return head + f"select 'raw' as metric, count(*) as n, round(avg(case when coalesce(pi, 0) = ti and coalesce(pd, 0) = td and coalesce(pn, 0) = tn then 1.0 else 0.0 end), 6) as value from ({c(true, 't')}) left join ({c(pred, 'p')}) using (chart_id)"
    if what == "strata":
        per = f"select s.share, case when h.chart_id is null then 'easy' else 'hard' end as hardness from ({per_chart(pred, true)}) s left join (select distinct chart_id from ({near_cut(SUP)})) h using (chart_id)"
        return head + f"select coalesce(hardness, 'total') as hardness, count(*) as n, round(avg(share), 6) as value from ({per}) group by rollup(hardness)"
    named = f"select t.chart_id, t.series_key, t.relation, p.relation as p from ({hsv(true, 'chart_id, series_key, relation')}) t join ({hsv(pred, 'chart_id, relation')}) p using (chart_id) where least(abs(t.h - p.h), 180 - abs(t.h - p.h)) <= 10"
    return head + f"select relation, count(*) filter (p = 'increasing') as as_increasing, count(*) filter (p = 'decreasing') as as_decreasing, count(*) filter (p = 'neutral') as as_neutral from ({named}) group by 1"


def theta_label(kind: str, points: str) -> str:
    sign = lambda e: f"case when {e} > 0 then 'increasing' when {e} < 0 then 'decreasing' else 'neutral' end"
    if kind == "corr3":
        return f"select chart_id, series_key, relation as label from ({relations_sql(points)})"
    if kind == "slope":
        return f"select chart_id, series_key, {sign('count(*) * sum(u * v) - sum(u) * sum(v)')} as label from (select chart_id, series_key, (x - min(x) over w)::hugeint as u, (y - min(y) over w)::hugeint as v from ({points}) window w as (partition by chart_id, series_key)) group by 1, 2"
    if kind == "kendall":
        pairs = f"select a.chart_id, a.series_key, sum(sign(b.y - a.y)) as s from ({points}) a join ({points}) b on a.chart_id = b.chart_id and a.series_key = b.series_key and a.x < b.x group by 1, 2"
        return f"select chart_id, series_key, {sign('coalesce(s, 0)')} as label from (select distinct chart_id, series_key from ({points})) left join ({pairs}) using (chart_id, series_key)"
    if kind == "pearson":
        s = f"""select chart_id, series_key, count(*)::double as n, sum(u)::double as su, sum(v)::double as sv, sum(u * v)::double as uv, sum(u * u)::double as uu, sum(v * v)::double as vv
          from (select chart_id, series_key, (x - min(x) over w)::hugeint as u, (y - min(y) over w)::hugeint as v from ({points}) window w as (partition by chart_id, series_key)) group by 1, 2"""
        t = f"select *, n * uv - su * sv as num, n * uu - su * su as vx, n * vv - sv * sv as vy from ({s})"
        return f"select chart_id, series_key, case when n < 2 or vx <= 0 then 'undefined' when vy <= 0 then 'neutral' when 25.0::double * num * num > 4.0::double * vx * vy then {sign('num')} else 'neutral' end as label from ({t})"
    return f"select chart_id, series_key, case when min(d) > 0 then 'increasing' when max(d) < 0 then 'decreasing' else 'neutral' end as label from (select chart_id, series_key, y - lag(y) over (partition by chart_id, series_key order by x, y) as d from ({points})) group by 1, 2"


def theta(kind: str) -> str:
    return f"select chart_id, series_key, '{kind}' as theta, label from ({theta_label(kind, POINTS_SQL['nation'])})"


def theta_counts() -> str:
    return " union all ".join(f"select '{k}' as theta, label, count(*) as n from ({theta_label(k, SUP)}) group by label" for k in ("corr3", "slope", "kendall", "monotone"))


def label_sql(key: str, attr: str, lo: int = 3, hi: int = 12) -> str:
    letter = f"substr('ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz', (concat('0x', substr(md5(concat_ws(':', {key}, '{attr}', i, '0')), 1, 8))::bigint % 52 + 1)::int, 1)"
    return f"substr((select string_agg({letter}, '' order by i) from range(1, {hi + 1}) r(i)), 1, ({draw_sql(key, f'{attr}-size')} % {hi - lo + 1} + {lo})::int)"


def style_columns(key: str, diverse: bool = True) -> str:
    pick = lambda attr, pool: f"{list(pool)}[({draw_sql(key, attr)} % {len(pool)}) + 1]"
    return f"""{key} as chart_id, {pick('type', TYPES)} as plot_type, {pick('style', STYLES) if diverse else "'plain'"} as style,
      {label_sql(key, 'title', 6)} as title, {label_sql(key, 'x_label')} as x_label, {label_sql(key, 'y_label')} as y_label,
      ({draw_sql(key, 'title_x')} % 60 + 20)::int as title_x, ({draw_sql(key, 'x_label_x')} % 60 + 30)::int as x_label_x,
      ({draw_sql(key, 'y_label_y')} % 40 + 14)::int as y_label_y, ({draw_sql(key, 'legend_y')} % 24 + 14)::int as legend_y"""


EMBEDDING_COLOURS = "select vec_id, label, greatest(0, least(255, floor((embedding[1]::double + 0.5) * 255)))::int as r, greatest(0, least(255, floor((embedding[2]::double + 0.5) * 255)))::int as g, greatest(0, least(255, floor((embedding[3]::double + 0.5) * 255)))::int as b from embeddings"
RELATION_TUPLES = f"select chart_id, 'ship year' as x_label, 'revenue of ' || s_name as y_label, series_key as series_label, relation from ({relations_sql(SUP)}) left join supplier on s_suppkey = chart_id"
SPEARMAN_PLAIN = f"""select chart_id, series_key, count(*) as n, case when count(*) > 1 then round(1 - 6 * sum(d * d) / (count(*) * (count(*) * count(*) - 1)), 6) end as rho from (
  select chart_id, series_key, (row_number() over (partition by chart_id, series_key order by x, y) - row_number() over (partition by chart_id, series_key order by y, x))::bigint as d from ({CUST3})) group by 1, 2"""
STYLES_ = f"select {style_columns('s_suppkey')} from supplier"
COLOURS = colours(CUST3)
TREND = f"""select chart_id, series_key, max(slope)::int as slope, sum(y + slope * floor(span * 2 * i / n)::bigint)::bigint as total, count(*) as n from (
  select *, ({draw_sql(_KEY, 'slope')} % 3 - 1) as slope, max(y) over w - min(y) over w + 1 as span, count(*) over w as n, row_number() over (partition by chart_id, series_key order by x, y) as i from ({SUP}) window w as (partition by chart_id, series_key)) group by 1, 2"""
SPECKLE = degraded(painted("scatter"))
HSV_EMBEDDINGS = f"select vec_id, r::int as r, g::int as g, b::int as b, h::int as h, s::int as s, v::int as v from ({hsv(EMBEDDING_COLOURS, 'vec_id')})"
HISTOGRAM = histogram(painted("line"))
DISTINCT = f"select chart_id, count(distinct (r, g, b)) as colours, count(*) as ink from ({degraded(painted('scatter', SUP, WIDE))}) group by 1"
ASSIGN = f"""with px as materialized ({EMBEDDING_COLOURS}), pts as (select r, g, b, count(*) as w from px group by all),
  means as (select label as cid, floor(avg(r))::int as cr, floor(avg(g))::int as cg, floor(avg(b))::int as cb from px group by 1),
  near as (select r, g, b, w, min(struct_pack(d := (r - cr) * (r - cr) + (g - cg) * (g - cg) + (b - cb) * (b - cb), cid := cid)) as m from pts, means group by all)
  select m.cid as cid, sum(w)::bigint as n, sum(w * m.d)::bigint as sse from near group by 1"""
CLEAN_CENTERS = clean_centers()
MASKS = f"select chart_id, series_no, count(*) as ink, sum(px)::bigint as sx, sum(py)::bigint as sy from ({masks()}) group by 1, 2"
OVERLAP = f"select chart_id, count(*) as pixels, count(*) filter (k > 1) as shared from (select chart_id, px, py, count(*) as k from ({marks('scatter')}) group by 1, 2, 3) group by 1"
PROGRAMMED = programmed()
BOUNDARY = near_cut(CUST3)
_SEEN = f"case when {draw_sql('p_name', 'confuse')} % 2 = 0 then translate(p_name, 'lI1O0oS5', '1lI0Oc5S') else p_name end"
EDIT = f"""with n as (select distinct p_name from part), s as (select distinct {_SEEN} as seen from n)
  select count(*) as n, count(*) filter (levenshtein(p_name, seen) <= 2) as within_2, count(*) filter (levenshtein(p_name, seen) <= 5) as within_5 from n, s"""


def _axis() -> str:
    seen = lambda c, seed: f"case when {draw_sql(c, 'confuse', seed)} % 3 = 0 then translate({c}, 'lI1O0oS5', '1lI0Oc5S') else {c} end"
    hit = lambda c, k: f"(levenshtein({c}, s{c}) <= {k})::int"
    row = lambda e: f"select 'axis' as metric, count(*) as n, round(avg({e}), 6) as value from p"
    both = lambda k: f"{hit('x_label', k)} * {hit('y_label', k)}"
    return f"""with t as materialized (select {style_columns('s_suppkey')} from supplier),
      p as (select x_label, y_label, {seen('x_label', 1)} as sx_label, {seen('y_label', 2)} as sy_label from t)
      {row(both(0))} union all {row(both(5))} union all {row(f"({hit('x_label', 0)} + {hit('y_label', 0)}) / 2.0")}"""


AXIS = _axis()


def legend_(anchor: str) -> str:
    m = f"""select chart_id, series_no, px, 20 + 11 * series_no + dy as py from ({colours(SUP)}), range(124, 130) a(px), (values (-1), (0), (1)) b(dy)
      union all select chart_id, series_no, px, py from ({painted('scatter')}) where px > 132 and py between 24 and 60"""
    if anchor == "median":
        m = f"select chart_id, series_no, quantile_cont(px, 0.5) as px, quantile_cont(py, 0.5) as py from ({m}) group by 1, 2"
    d = "((140 - m.px) * (140 - m.px) + (t.cy - m.py) * (t.cy - m.py))::double"
    return f"""select chart_id, ordinal, text, b.s as series_no, b.d as d2 from (
      select t.chart_id, t.ordinal, t.text, min(struct_pack(d := {d}, s := m.series_no)) as b
      from (select chart_id, series_no as ordinal, series_key as text, 20 + 11 * series_no as cy from ({colours(SUP)})) t join ({m}) m on t.chart_id = m.chart_id group by 1, 2, 3)"""


_TRACE = f"select chart_id, px::bigint as x, (-floor(sum(py) * 1000 / count(*)))::bigint as y from ({painted('line')}) group by chart_id, px"
TURNS = f"""with t as (select chart_id, x, y, sign(y - lag(y) over w) as s0, sign(lead(y) over w - y) as s1 from ({_TRACE}) window w as (partition by chart_id order by x)),
  u as (select *, last_value(case when s0 <> 0 then s0 end ignore nulls) over (partition by chart_id order by x rows between unbounded preceding and current row) as before from t)
  select chart_id, x, y from u where s0 is null or s1 is null or (s1 <> 0 and before is not null and s1 <> before)"""
INTERPOLATED = f"""select chart_id, 'all' as series_key, spot as x, (y + ((y1 - y) * (spot - x)) // greatest(1, x1 - x))::bigint as y from (
  select *, unnest(range(x, case when x1 > x then x1 else x + 1 end, 2)) as spot from (
    select chart_id, x, y, coalesce(lead(x) over w, x) as x1, coalesce(lead(y) over w, y) as y1 from ({TURNS}) window w as (partition by chart_id order by x)))"""
EXTRACTOR = f"select chart_id, relation from ({relations_sql(INTERPOLATED)})"
GUESS = f"select ['increasing', 'decreasing', 'neutral'][({draw_sql(_KEY, 'guess')} % 3) + 1] as relation, count(*) as n from (select distinct chart_id, series_key from ({CUST3})) group by 1"
MAJORITY = f"""with t as (select relation, count(*) as n from ({relations_sql(CUST3)}) where relation <> 'undefined' group by 1), top as (select relation from t order by n desc, relation limit 1)
  select sum(n)::bigint as n, round(avg(case when relation = (from top) then 1.0 else 0.0 end), 6) as balanced, round(sum(case when relation = (from top) then n else 0 end) / sum(n), 6) as plain, round(max(n) / sum(n), 6) as majority from t"""


def eligible(points: str) -> str:
    """Line charts of up to three series, each at least 60 % of the height tall, of colours farther apart than the ranges are wide."""
    tall = f"""select chart_id from (select chart_id, count(*) as k, min(hi - lo) as least, max(hi) - min(lo) as span from (
      select chart_id, series_key, min(y) as lo, max(y) as hi from ({points}) group by 1, 2) group by 1) where k <= 3 and span > 0 and 10 * least >= 6 * span"""
    c = hsv(drawn_colours(points), "chart_id, series_no")
    close = f"""select a.chart_id from ({c}) a join ({c}) b on a.chart_id = b.chart_id and a.series_no < b.series_no
      where least(abs(a.h - b.h), 180 - abs(a.h - b.h)) <= 10 and abs(a.s - b.s) <= 25 and abs(a.v - b.v) <= 40"""
    kind = f"{list(TYPES)}[({draw_sql('chart_id', 'type')} % {len(TYPES)}) + 1]"
    return f"select chart_id from ({tall}) t anti join ({close}) c using (chart_id) where {kind} = 'line'"


FILTERED = eligible(SUP)
SPLIT = f"select chart_id, case when n <= 100 then 'transfer_test' when n <= 200 then 'control_train' else 'control_test' end as role from (select chart_id, row_number() over (order by chart_id) as n from ({eligible(CUST3)})) where n <= 300"
_USER = POINTS_SQL["user"]
HARDNESS = f"""select m.chart_id, m.series, coalesce(n.near, 0) as near, round(o.shared, 6) as shared, (m.series > 3 or n.near is not null or 10 * o.many > 3 * o.pixels) as hard from
  (select chart_id, count(distinct series_key) as series from ({_USER}) group by 1) m left join (select chart_id, count(*) as near from ({near_cut(_USER)}) group by 1) n using (chart_id)
  join (select chart_id, count(*) as pixels, count(*) filter (k > 1) as many, count(*) filter (k > 1) / count(*) as shared from (select chart_id, px, py, count(*) as k from ({marks('line', _USER, WIDE)}) group by 1, 2, 3) group by 1) o using (chart_id)"""
PROPS = "select event_type, count(json_extract_string(props, '$.k')) as n, sum(json_extract_string(props, '$.k')::bigint)::bigint as total from events group by 1"
TITLES = "select page_id, trim(regexp_extract(html, '(?is)<title[^>]*>(.*?)</title>', 1)) as title from pages"
SESSIONS = """select user_id, count(*) as sessions, max(n) as longest from (select user_id, s, count(*) as n from (
  select user_id, sum(new) over (partition by user_id order by ts, event_id rows between unbounded preceding and current row) as s from (
    select user_id, ts, event_id, case when lag(ts) over (partition by user_id order by ts, event_id) + interval 30 minute > ts then 0 else 1 end as new from events)) group by 1, 2) group by 1"""
WINDOWED = relations_sql(f"select x // 86400000000 as chart_id, series_key, x, y from ({POINTS_SQL['user']})")
_B = f"select chart_id from ({POINTS_SQL['customer']}) group by 1 having count(*) >= 8"
SETS = f"""with a as materialized ({eligible(CUST3)}), b as materialized ({_B})
  select 'both' as part, count(*) as n, coalesce(sum(chart_id), 0)::bigint as total from (select * from a intersect select * from b)
  union all select 'first_only', count(*), coalesce(sum(chart_id), 0)::bigint from (select * from a except select * from b)
  union all select 'either', count(*), coalesce(sum(chart_id), 0)::bigint from (select * from a union select * from b)"""
DISJOINT = f"""with s as materialized ({SPLIT}) select count(*) as n, count(distinct chart_id) as charts, (count(*) - count(distinct chart_id))::bigint as shared,
  count(*) filter (role = 'transfer_test') as transfer_test, count(*) filter (role = 'control_train') as control_train, count(*) filter (role = 'control_test') as control_test from s"""
LABELS = f"select chart_id, series_key, {label_sql(_KEY, 'legend', 3, 9)} as label from (select distinct chart_id, series_key from ({CUST3}))"
OVERDRAWN = f"""with m as materialized ({marks('line')}), top as (select chart_id, px, py, max(series_no) as t from m group by 1, 2, 3)
  select chart_id, series_no, count(*) as drawn, count(*) filter (t > series_no) as hidden from m join top using (chart_id, px, py) group by 1, 2"""
_UP = "((h % 30) * 255 + 15) // 30"
_HUES = f"""select chart_id, 1 as series_no, [255, 255 - {_UP}, 0, 0, {_UP}, 255][h // 30 + 1] as r, [{_UP}, 255, 255, 255 - {_UP}, 0, 0][h // 30 + 1] as g, [0, 0, {_UP}, 255, 255, 255 - {_UP}][h // 30 + 1] as b
  from ({hsv(f"select vec_id as chart_id, r, g, b from ({EMBEDDING_COLOURS})")}) where h < 15 or h > 165"""
WRAPPED = ranges(of=_HUES)
_BOX = "least({n}, 6 * len({t}) - 1)"


def _facets() -> str:
    st = f"select {style_columns('s_suppkey')} from supplier"
    box = lambda n, t: _BOX.format(n=n, t=t)
    row = lambda kind, text, x, y, w, h: f"select chart_id, '{kind}' as kind, 0 as ordinal, ({x})::int as x0, ({y})::int as y0, ({x} + {w})::int as x1, ({y} + {h})::int as y1, {text} as text from st where chart_id in (select chart_id from ({SUP}))"
    legend = f"""select chart_id, 'legend_text' as kind, (series_no - 1)::int as ordinal, 173 as x0, (legend_y + 11 * (series_no - 1))::int as y0, (173 + {box('77', 'label')})::int as x1, (legend_y + 11 * (series_no - 1) + 7)::int as y1, label as text
      from (select chart_id, series_no, {label_sql(_KEY, 'legend', 3, 9)} as label from ({colours(SUP)})) join st using (chart_id)"""
    return f"""with st as materialized ({st}) {row('title', 'title', 'title_x', '2', box('250 - title_x', 'title'), '7')} union all {row('x_label', 'x_label', 'x_label_x', '135', box('250 - x_label_x', 'x_label'), '7')}
      union all {row('y_label', 'y_label', '2', 'y_label_y', '7', box('144 - y_label_y', 'y_label'))} union all {legend}"""


FACETS = _facets()


def styled(kind: str, style: str, points: str = SUP, pool=RGB3, only: str = "") -> str:
    """Ink of charts of one type in one style; ``only`` restricts to charts of a query."""
    use = f"select * from ({points}) where chart_id in ({only})" if only else points
    m = marks(kind, use, pool)
    if style == "dashed" and kind == "line":
        m = f"select * from ({m}) where px % 8 < 4"
    if style == "wide_line" and kind != "bar":
        m = f"select distinct chart_id, series_no, px + dx as px, py + dy as py from ({m}), (values (-1), (0), (1)) a(dx), (values (-1), (0), (1)) b(dy)"
    if style == "markers" and kind == "line":
        m = f"{m} union {marks('scatter', use, pool)}"
    c = f"select chart_id, series_no, r, g, b from ({colours(use, pool)})"
    if style == "grid":
        ids = f"select distinct chart_id from ({use})"
        m = f"select chart_id, series_no, px, py from ({m}) union all select chart_id, 0, x, y from ({ids}), range(20, 140) a(x), range(14, 104) b(y) where (x - 20) % 15 = 0 or (y - 14) % 15 = 0"
        c = f"{c} union all select chart_id, 0, 200, 200, 200 from ({ids})"
    return f"select chart_id, px::int as px, py::int as py, nullif(series_no, 0)::int as series_no, r, g, b, {'true' if style == 'dark' else 'false'} as dark from (select chart_id, px, py, max(series_no) as series_no from ({m}) group by 1, 2, 3) join ({c}) c using (chart_id, series_no)"


def mixed() -> str:
    """Ink of every chart in its own drawn type and style, summed up per chart."""
    st = f"select {style_columns('s_suppkey')} from supplier"
    parts = " union all ".join(f"select *, '{k}' as plot_type, '{y}' as style from ({styled(k, y, SUP, RGB3, chr(32).join(['select chart_id from st where plot_type =', repr(k), 'and style =', repr(y)]))})" for k in TYPES for y in STYLES)
    return f"""with st as materialized (select chart_id, plot_type, style from ({st})) select chart_id, plot_type, style, dark, count(*) as ink, count(*) filter (series_no is null) as gray, sum(px)::bigint as sx, sum(py)::bigint as sy, count(distinct (r, g, b)) as colours from ({parts}) group by 1, 2, 3, 4"""


def labelled_pred() -> str:
    """Predicted relations under the labels that a confusing reader sees, and the truth with its labels (tables pred, tru)."""
    seen = f"case when {draw_sql('label', 'confuse')} % 2 = 0 then translate(label, 'lI1O0oS5', '1lI0Oc5S') else label end"
    return f"""with prog as materialized ({programmed()}), tru as materialized (select *, {label_sql(_KEY, 'legend', 3, 9)} as label from ({true_series()})),
      pred as materialized (select t.chart_id, t.series_no as no, {seen} as seen, p.relation as pr from ({hsv('select * from tru', 'chart_id, series_key, series_no, label')}) t join ({hsv('select * from prog', 'chart_id, relation')}) p using (chart_id)
        where least(abs(t.h - p.h), 180 - abs(t.h - p.h)) <= 10),
      near as (select t.chart_id, t.series_key, t.relation, p.no, p.pr, levenshtein(p.seen, t.label) as d from tru t join pred p using (chart_id) where levenshtein(p.seen, t.label) <= 2),
      a as (select * from near qualify row_number() over (partition by chart_id, series_key order by d, no, series_key) = 1),
      b as (select * from a qualify row_number() over (partition by chart_id, no order by d, no, series_key) = 1),
      share as (select t.chart_id, avg(case when b.pr = t.relation then 1.0 else 0.0 end) as share from (select * from tru where relation <> 'undefined') t left join b on t.chart_id = b.chart_id and t.series_key = b.series_key group by 1),
      series as (select count(*) as n, round(avg(share), 6) as value from share)"""


SERIES_ACCURACY = f"{labelled_pred()} select 'series' as metric, n, value from series"
TOTAL_ACCURACY = f"""{labelled_pred()}, ax as (select n, value from ({_axis()}) limit 1 offset 1)
  select 'total' as metric, greatest(s.n, ax.n) as n, round((s.value + ax.value) / 2, 6) as value from series s, ax"""
DELTA = f"""select a.metric, a.value as a, b.value as b, round(b.value - a.value, 6) as delta from ({score('no_ocr')}) a join ({score('boundary')}) b using (metric)"""
CAUSES = f"""with t as materialized (select {style_columns('s_suppkey')} from supplier),
  p as (select chart_id, 'x' as axis, x_label as label, case when {draw_sql('x_label', 'confuse', 1)} % 3 = 0 then translate(x_label, 'lI1O0oS5', '1lI0Oc5S') else x_label end as seen, y_label as other from t
        union all select chart_id, 'y', y_label, case when {draw_sql('y_label', 'confuse', 2)} % 3 = 0 then translate(y_label, 'lI1O0oS5', '1lI0Oc5S') else y_label end, x_label from t),
  q as (select *, case when chart_id % 7 = 0 then '' when chart_id % 11 = 0 then other else seen end as found from p)
  select axis, case when found = '' then 'facet_missed' when found = label then 'exact' when levenshtein(found, other) <= 5 and levenshtein(found, label) > 5 then 'facets_swapped'
    when levenshtein(found, label) <= 5 then 'misread_within_limit' else 'misread' end as cause, count(*) as n from q group by 1, 2"""
MASK_QUALITY = f"""with m as materialized ({masks()}), c as materialized ({clean_centers()}), t as materialized ({painted('line')}),
  own as (select p.chart_id, p.series_no as found, t.series_no from ({hsv('select chart_id, series_no, r, g, b from c', 'chart_id, series_no')}) p join ({hsv(colours(SUP), 'chart_id, series_no')}) t on p.chart_id = t.chart_id and least(abs(t.h - p.h), 180 - abs(t.h - p.h)) <= 10),
  hit as (select o.chart_id, o.series_no, count(*) as n from own o join m on m.chart_id = o.chart_id and m.series_no = o.found join t on t.chart_id = o.chart_id and t.series_no = o.series_no and t.px = m.px and t.py = m.py group by 1, 2),
  got as (select o.chart_id, o.series_no, count(*) as n from own o join m on m.chart_id = o.chart_id and m.series_no = o.found group by 1, 2),
  want as (select chart_id, series_no, count(*) as n from t group by 1, 2)
  select w.chart_id, w.series_no, round(coalesce(h.n, 0) / g.n, 6) as precision, round(coalesce(h.n, 0) / w.n, 6) as recall from want w left join got g using (chart_id, series_no) left join hit h using (chart_id, series_no)"""


def legend_accuracy() -> str:
    return " union all ".join(f"select '{a}' as anchor, count(*) as n, round(avg(case when ordinal = series_no then 1.0 else 0.0 end), 6) as value from ({legend_(a)})" for a in ("median", "nearest"))


def text_only() -> str:
    """The relation that is commonest among training series whose label begins alike, for the others."""
    return f"""with t as materialized (select chart_id, series_key, relation, lower(substr({label_sql(_KEY, 'legend', 3, 9)}, 1, 1)) as token, {draw_sql('chart_id', 'half')} % 2 as half from ({relations_sql(CUST3)}) where relation <> 'undefined'),
      whole as (select relation from (select relation, count(*) as n from t where half = 0 group by 1) order by n desc, relation limit 1),
      known as (select token, relation from (select token, relation, count(*) as n from t where half = 0 group by 1, 2) qualify row_number() over (partition by token order by n desc, relation) = 1),
      g as (select t.relation, coalesce(k.relation, (from whole)) as guess from t left join known k using (token) where half = 1)
      select count(*) as n, round(avg(case when relation = guess then 1.0 else 0.0 end), 6) as value from g"""
