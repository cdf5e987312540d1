"""DuckDB SQL for the workloads, written independently of the DataFrame code over the same tables."""

from __future__ import annotations

import re

STEPS, SETTLED = 15, 60

_VIEWS = {
    "posts": (
        "select o_orderkey as post_id, o_custkey as author_id, cast(o_orderdate as date) as day, x / sqrt(x * x + 15) as "
        "sentiment from (select *, 4 * (o_totalprice - 250000) / 250000 as x from orders)"
    ),
    "members": (
        "select * from (select post_id, topic_id, q / sum(q) over (partition by post_id) as p from (select l_orderkey as "
        "post_id, cast(substr(p_brand, 7) as int) as topic_id, sum(l_quantity) as q from lineitem join part on l_partkey = "
        "p_partkey group by all)) where p >= 0.01"
    ),
    "grp": (
        "select cast(t as int) as topic_id, cast(t % 5 as int) as group_id from range(1, 24) r(t) union all select cast(t as "
        "int), cast((t + 1) % 5 as int) from range(1, 24) r(t) where t % 7 = 0"
    ),
    "incidents": (
        "select cast(l_shipdate as date) as day, n_regionkey as group_id, n_name as motive, r_name as category, p_type as "
        "offence, l_quantity as severity from lineitem join supplier on l_suppkey = s_suppkey join nation on s_nationkey = "
        "n_nationkey join region on n_regionkey = r_regionkey join part on l_partkey = p_partkey where l_returnflag = 'R'"
    ),
    "clipped": "select * from incidents where day between date '1995-01-01' and date '2001-08-01'",
    "grouped": (
        "select posts.*, g.group_id from posts join (select distinct post_id, group_id from members join grp using (topic_id)) "
        "g using (post_id)"
    ),
    "daily": (
        "select group_id, day, count(*) as n_posts, avg(sentiment) as mean_score, avg(case when abs(sentiment) > 0.5 then 1.0 "
        "else 0.0 end) as strong_share, sum(sentiment) as sum_score from grouped group by all"
    ),
    "dinc": "select group_id, day, count(*) as n_incidents from incidents group by all",
    "spine": "select cast(d as date) as day from generate_series(date '1995-01-01', date '2001-08-01', interval 1 day) t(d)",
    "pdense": (
        "select s.group_id, s.day, coalesce(n_posts, 0) as n_posts, mean_score, strong_share, coalesce(sum_score, 0) as "
        "sum_score from (select group_id, day from (select distinct group_id from daily), spine) s left join daily using "
        "(group_id, day)"
    ),
    "idense": (
        "select s.group_id, s.day, coalesce(n_incidents, 0) as n_incidents from (select group_id, day from (select distinct "
        "group_id from dinc), spine) s left join dinc using (group_id, day)"
    ),
    "prolled": (
        "select group_id, day, case when count(*) over w >= 5 then avg(n_posts) over w end as r_posts, case when count(*) over "
        "w >= 5 then avg(mean_score) over w end as r_score, case when count(*) over w >= 5 then avg(strong_share) over w end "
        "as r_strong from pdense window w as (partition by group_id order by day rows between 29 preceding and current row)"
    ),
    "irolled": (
        "select group_id, day, case when count(*) over w >= 5 then avg(n_incidents) over w end as r_incidents from idense "
        "window w as (partition by group_id order by day rows between 29 preceding and current row)"
    ),
    "paired": "select group_id, day, r_posts, r_score, r_strong, r_incidents from prolled left join irolled using (group_id, day)",
    "focal": "select * from paired where group_id in (0, 3)",
    "long": (
        "select group_id, day, 'r_posts' as measure, round(r_posts, 9) as value, round(r_incidents, 9) as r_incidents from "
        "focal union all select group_id, day, 'r_score', round(r_score, 9), round(r_incidents, 9) from focal union all select "
        "group_id, day, 'r_strong', round(r_strong, 9), round(r_incidents, 9) from focal"
    ),
    "calendar": "select cast(g as int) as group_id, make_date(1996 + k, 3 + g, 15) as event_day from range(0, 5) a(g), range(0, 3) b(k)",
    "docs": (
        "select doc_id, text, lang, trim(regexp_replace(regexp_replace(lower(text), '[^\\p{L}\\p{N}\\s]', '', 'g'), '\\s+', ' "
        "', 'g')) as clean, trim(regexp_replace(regexp_replace(lower(text), '[^\\p{L}\\p{N}\\s-]', '', 'g'), '\\s+', ' ', "
        "'g')) as hyphened from documents"
    ),
    "four": (
        "select array_to_string(w[1:4], ' ') as term from (select string_split(trim(regexp_replace(regexp_replace(lower(text), "
        "'[^\\p{L}\\p{N}\\s]', '', 'g'), '\\s+', ' ', 'g')), ' ') as w from benchmark) where len(w) >= 4"
    ),
    "ten": "select unnest(['idiot', 'moron', 'clown', 'scum', 'worthless', 'pathetic', 'stupid', 'trash', 'loser', 'disgusting']) as term",
    "phrases": "select term from ten union select term from four",
    "tokens": "select doc_id, string_split(clean, ' ') as w from docs",
    "matched": (
        "select distinct doc_id, term from (select doc_id, unnest(w) as term from tokens union all select doc_id, "
        "array_to_string(w[i:i + 3], ' ') from tokens, unnest(range(1, len(w) - 2)) u(i)) join phrases using (term)"
    ),
    "reposts": "select event_id as post_id, event_id % (select count(*) from documents) as doc_id from events",
    "active": "select author_id as user_id, count(*) as n_posts, avg(sentiment) as mean_score from posts group by 1 having count(*) >= 10",
    "profile": (
        "select author_id as user_id, topic_id, sum(p) as s from posts join members using (post_id) where author_id in (select "
        "user_id from active) group by all"
    ),
    "bygroup": "select group_id, user_id, topic_id, s from profile join grp using (topic_id)",
    "restricted": "select group_id, user_id, topic_id, s from profile join grp using (topic_id) where group_id in (0, 3)",
    "everyone": (
        "select group_id, author_id as user_id, topic_id, sum(p) as s from posts join members using (post_id) join grp using "
        "(topic_id) where group_id in (0, 3) group by all"
    ),
    "fans": "select c_custkey as user_id, greatest(0, cast(floor(c_acctbal) as bigint)) as followers from customer",
    "inf": (
        f"select group_id, user_id, x as centrality, followers, n_posts, mean_score as score, x * ln(followers + 1.0) as "
        f"influence from x{STEPS} join active using (user_id) join fans using (user_id)"
    ),
    "top": (
        "select * from (select *, row_number() over (partition by group_id order by round(influence, 9) desc, user_id) as rank "
        "from inf) where rank <= 5"
    ),
    "bins": (
        "select group_id, b / 10.0 as bin_lo, n, mean, se, row_number() over (partition by group_id order by round(mean, 9) "
        "desc, b) = 1 as is_peak from (select group_id, cast(floor(round(score * 10, 9)) as bigint) as b, count(*) as n, "
        "avg(influence) as mean, stddev_samp(influence) / sqrt(count(*)) as se from inf group by all having count(*) >= 10)"
    ),
    "emb": "select vec_id, label, unnest(embedding)::double as v, unnest(range(1, len(embedding) + 1)) as i from embeddings",
    "center": (
        "select topic_id, i, m / sqrt(sum(m * m) over (partition by topic_id)) as c from (select label as topic_id, i, avg(v) "
        "as m from emb group by all)"
    ),
    "soft": (
        "select vec_id, topic_id, e / sum(e) over (partition by vec_id) as p from (select vec_id, topic_id, exp(sum(v * c) / "
        "0.05) as e from emb join center using (i) group by all)"
    ),
    "lab": (
        "select label as topic_id, string_split(trim(regexp_replace(regexp_replace(lower(text), '[^\\p{L}\\p{N}\\s]', '', "
        "'g'), '\\s+', ' ', 'g')), ' ') as w, text from documents join embeddings on doc_id = vec_id"
    ),
    "tf": (
        "select topic_id, term, count(*) as tf from (select topic_id, array_to_string(w[i:i + k - 1], ' ') as term from lab, "
        "range(1, 4) r(k), unnest(range(1, len(w) - k + 2)) u(i)) where term <> '' group by all"
    ),
    "weights": (
        "select topic_id, term, tf * ln(1 + a / al) as weight from tf join (select term, sum(tf) as al from tf group by 1) "
        "using (term), (select sum(tf) / count(distinct topic_id) as a from tf)"
    ),
    "ranked": "select *, row_number() over (partition by topic_id order by round(weight, 8) desc, term) as rank from weights",
    "weekly": "select topic_id, cast(date_trunc('week', day) as date) as week, count(*) as n from members join posts using (post_id) group by all",
    "shares": "select topic_id, week, n, n / sum(n) over (partition by topic_id) as share from weekly",
    "picked": (
        "select group_id, topic_id from (select *, row_number() over (partition by group_id order by (topic_id * 7) % 23, "
        "topic_id) as r from grp) where r <= 2"
    ),
    "heat": "select group_id, topic_id, week, n, share from shares join picked using (topic_id)",
    "keyed": (
        "select concat_ws('|', cast(day as varchar), motive, offence, cast(cast(severity as bigint) as varchar), "
        "cast(row_number() over (partition by day, motive, offence, severity order by group_id) as varchar)) as incident_id, "
        "day, group_id from clipped"
    ),
    "relevant": "select distinct post_id from members where topic_id in (select topic_id from grp) and post_id in (select post_id from posts)",
    "kept": "select * from posts where post_id in (select post_id from relevant)",
    "ev": "select event_id, ts, user_id, event_type, value, cast(json_extract_string(props, '$.k') as int) as k from events",
    "replies": (
        "select user_id as src_user, dst as dst_user, cast(ts as date) as day from (select *, lag(user_id) over w as dst, "
        "lag(ts) over w as before from ev window w as (partition by k order by ts, event_id)) where dst <> user_id and "
        "epoch_us(ts) - epoch_us(before) <= 3600000000"
    ),
    "pagelinks": (
        "select regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) as src_user, unnest(list_distinct(regexp_extract_all(html, "
        "'href=\"/([^\"]*)\"', 1))) as dst_user from pages"
    ),
    "edges": """
        select 'user:' || author_id as src, 'post:' || post_id as dst, 'tweeted' as rel, 1.0::double as weight from kept
        union all select 'post:' || post_id, 'date:' || cast(day as varchar), 'tweeted_on', 1.0 from kept
        union all select 'post:' || post_id, 'topic:' || topic_id, 'in_topic', p from members where topic_id in (select topic_id from grp) and post_id in (select post_id from kept)
        union all select 'incident:' || incident_id, 'date:' || cast(day as varchar), 'occurred_on', 1.0 from keyed
        union all select 'incident:' || incident_id, 'group:' || group_id, 'victimized', 1.0 from keyed
        union all select 'topic:' || topic_id, 'group:' || group_id, 'associated_with', 1.0 from grp
        union all select distinct 'post:' || event_id, 'hashtag:k' || k, 'has_hashtag', 1.0 from ev where event_id in (select post_id from kept)
        union all select 'user:' || src_user, 'user:' || dst_user, 'replied_to', count(*) from replies group by all
        union all select 'user:' || src_user, 'user:' || dst_user, 'mentioned', count(*) from pagelinks group by all""",
    "nodes": "select distinct node_id, string_split(node_id, ':')[1] as kind from (select src as node_id from edges union all select dst from edges)",
    "snapstream": (
        "select period, least(a, b) as src, greatest(a, b) as dst, cast(count(*) as double) as weight from (select "
        "cast(date_trunc('week', day) as date) as period, 'user:' || src_user as a, 'user:' || dst_user as b from replies) "
        "group by all"
    ),
    "g0": "select topic_id from grp where group_id = 0",
    "half": (
        "select members.post_id, topic_id, author_id, cast(date_trunc('month', day) as date) as period from members join g0 "
        "using (topic_id) join posts using (post_id) where day between date '1996-01-01' and date '1996-06-30'"
    ),
    "year": (
        "select members.post_id, topic_id, p, author_id, cast(date_trunc('quarter', day) as date) as period from members join "
        "posts using (post_id) where topic_id in (select topic_id from g0) and day between date '1996-01-01' and date "
        "'1996-12-31'"
    ),
    "snapyear": (
        "select period, least(a, b) as src, greatest(a, b) as dst, sum(w) as weight from (select distinct period, 'user:' || "
        "author_id as a, 'post:' || post_id as b, 1.0::double as w from year union all select period, 'post:' || post_id, "
        "'topic:' || topic_id, 1.0 from year) group by all"
    ),
    "given": """
        select period, 'post:' || post_id as node, topic_id as community from (select period, post_id, topic_id, row_number() over (partition by period, post_id order by round(sum(p), 9) desc, topic_id) as r from year group by period, post_id, topic_id) where r = 1
        union all select period, 'user:' || author_id, topic_id from (select period, author_id, topic_id, row_number() over (partition by period, author_id order by round(sum(p), 9) desc, topic_id) as r from year group by period, author_id, topic_id) where r = 1
        union all select distinct period, 'topic:' || topic_id, topic_id from year""",
    "domgroup": (
        "select period, group_id as community, author_id as user_id from (select cast(date_trunc('quarter', day) as date) as "
        "period, author_id, group_id, row_number() over (partition by date_trunc('quarter', day), author_id order by "
        "round(sum(p), 9) desc, group_id) as r from members join posts using (post_id) join grp using (topic_id) group by "
        "date_trunc('quarter', day), author_id, group_id) where r = 1 qualify count(*) over (partition by period, community) "
        ">= 50"
    ),
    "domtopic": (
        "select period, topic_id as community, author_id as user_id from (select cast(date_trunc('month', day) as date) as "
        "period, author_id, topic_id, row_number() over (partition by date_trunc('month', day), author_id order by "
        "round(sum(p), 9) desc, topic_id) as r from members join posts using (post_id) group by date_trunc('month', day), "
        "author_id, topic_id) where r = 1 qualify count(*) over (partition by period, community) >= 5"
    ),
}

_VALUES = {
    "idiot": -2.3, "moron": -2.2, "clown": -1.6, "scum": -2.9, "worthless": -1.9, "pathetic": -2.4, "stupid": -2.4, "trash": -1.7, "loser": -2.4, "disgusting": -3.1,
    "thing": 0.9, "ering": 1.4, "ther": 1.9, "tion": 2.4, "être": 1.1, "ment": 1.6, "lich": 1.2, "ung": 1.8, "ción": 1.3, "ado": 0.9,
}


def _sentiment(rules: bool) -> str:
    values = ", ".join(f"('{w}', {v})" for w, v in _VALUES.items())
    head = f"""with lex(word, v) as (values {values}),
b as (select doc_id, text as body from documents),
t as (select doc_id, body, unnest(l) as w, unnest(range(1, len(l) + 1)) as i from (select *, regexp_extract_all(body, '[\\p{{L}}\\p{{N}}'']+') as l from b)),
"""
    if not rules:
        return head + """s as (select doc_id, sum(v) as x from t join lex on word = lower(w) group by 1)
select event_id as post_id, round(coalesce(x, 0) / sqrt(coalesce(x, 0) * coalesce(x, 0) + 15), 6) + 0.0 as score
from (select event_id, event_id % (select count(*) from documents) as doc_id from events) join b using (doc_id) left join s using (doc_id)"""
    near = lambda d: f"coalesce(lag(lw, {d}) over o, '')"
    degree = lambda d, damp: f"{damp} * case {near(d)} when 'the' then 0.293 when 'of' then 0.293 when 'and' then -0.293 else 0 end"
    denied = " or ".join(f"{near(d)} in ('not', 'is', 'nicht', 'non')" for d in (1, 2, 3))
    return head + f"""u as (select *, lower(w) as lw, upper(w) = w and lower(w) <> w and len(w) > 1 as loud from t),
q as (select *, bool_or(not loud) over (partition by doc_id) as mixed, min(case when lw in ('to', 'mais', 'aber', 'pero') then i end) over (partition by doc_id) as turn,
    {degree(1, 1.0)} + {degree(2, 0.95)} + {degree(3, 0.9)} as deg, {denied} as denied from u window o as (partition by doc_id order by i)),
z as (select doc_id, i, turn, denied, v + sign(v) * (case when loud and mixed then 0.733 else 0 end + deg) as y from q join lex on word = lw),
s as (select doc_id, sum(y * case when denied then -0.74 else 1 end * case when turn is null or i = turn then 1 when i < turn then 0.5 else 1.5 end) as x from z group by 1),
m as (select b.doc_id, coalesce(x, 0) as x, least(len(body) - len(replace(body, '!', '')), 4) * 0.292 as ex, len(body) - len(replace(body, '?', '')) as qs from b left join s using (doc_id)),
f as (select doc_id, x + sign(x) * (ex + case when qs > 3 then 0.96 when qs > 1 then qs * 0.18 else 0 end) as x from m)
select event_id as post_id, round(x / sqrt(x * x + 15), 6) + 0.0 as score from (select event_id, event_id % (select count(*) from documents) as doc_id from events) join f using (doc_id)"""


def _spearman(source: str, x: str, y: str, by: str) -> str:
    ranks = ", ".join(f"rank() over (partition by {by} order by {c}) + (count(*) over (partition by {by}, {c}) - 1) / 2.0 as {n}" for c, n in ((x, "rx"), (y, "ry")))
    return (
        f"select {by}, count(*) as n, round(case when stddev_pop(rx) > 0 and stddev_pop(ry) > 0 then corr(rx, ry) end, 6) + 0.0 "
        f"as r_s from (select {by}, {ranks} from ({source}) where {x} is not null and {y} is not null) group by {by}"
    )


def _with_p(correlations: str, steps: int = 20_000) -> str:
    """Two-sided p of t on n - 2 degrees of freedom, as a share of the integral of a power of the cosine (Simpson's rule)."""
    area = lambda a: (
        f"(select sum(pow(cos({a} + (pi() / 2 - {a}) * i / {steps}), n - 3) * case when i in (0, {steps}) then 1 when i % 2 = 1 "
        f"then 4 else 2 end) * (pi() / 2 - {a}) from range(0, {steps + 1}) g(i))"
    )
    strength = "case when abs(r_s) < 0.1 then 'none' when abs(r_s) < 0.4 then 'weak' when abs(r_s) < 0.7 then 'moderate' else 'strong' end"
    sign = "case when abs(r_s) >= 0.1 then case when r_s > 0 then 'positive' else 'negative' end end"
    reading = f"concat_ws(' ', {strength}, {sign}, case when p < 0.05 then 'significant' else 'not significant' end)"
    return (
        f"select group_id, measure, n, round(r_s, 6) + 0.0 as r_s, round(p, 6) + 0.0 as p, {reading} as reading from (select *, "
        f"{area('asin(abs(r_s))')} / {area('0')} as p from ({correlations}))"
    )


def _power() -> dict[str, str]:
    """The unrolled steps: x0, then topic totals, products and unit vectors; enough of them to settle."""
    views = {"own": "select group_id, user_id, sum(s * s) as own from restricted group by all", "x0": "select group_id, user_id, 1.0::double as x from own"}
    for k in range(1, SETTLED + 1):
        views[f"t{k}"] = f"select group_id, topic_id, sum(s * x) as t from restricted join x{k - 1} using (group_id, user_id) group by all"
        views[f"y{k}"] = (
            f"select group_id, user_id, y - own * x as y from (select group_id, user_id, sum(s * t) as y from restricted join t{k} "
            f"using (group_id, topic_id) group by all) join own using (group_id, user_id) join x{k - 1} using (group_id, user_id)"
        )
        views[f"x{k}"] = f"select group_id, user_id, y / sqrt(sum(y * y) over (partition by group_id)) as x from y{k}"
    return views


def with_views(sql: str) -> str:
    """``sql`` led by the views that it names, each after those it needs."""
    views, order = _VIEWS | _power(), []

    def need(text: str) -> None:
        for name in dict.fromkeys(re.findall(r"\b[a-z_]+\d*\b", text)):
            if name in views and name not in order and re.search(rf"(?:\bfrom|\bjoin|,)\s*{name}\b", text):
                need(views[name])
                if name not in order:
                    order.append(name)

    need(sql)
    return (f"with {', '.join(f'{n} as materialized ({views[n]})' for n in order)} " if order else "") + sql


def workload_sql() -> dict[str, str]:
    plural = (
        "case when regexp_matches(base, '(s|x|z|ch|sh)$') then base || 'es' when regexp_matches(base, '[^aeiou]y$') then "
        "regexp_replace(base, 'y$', 'i') || 'es' else base || 's' end"
    )
    terms = "('idiot'), ('worthless clown'), ('black box'), ('city'), ('box of lies'), ('match'), ('toy'), ('press')"
    r = lambda x: f"round({x}, 6) + 0.0"
    sql = {
        "w01_clean_text": "select doc_id, md5(clean) as clean_hash from docs",
        "w02_expand_terms": (
            f"select distinct base, unnest([f, replace(f, ' ', ''), replace(f, ' ', '-')]) as term from (select base, unnest([base, "
            f"{plural}]) as f from (values {terms}) t(base))"
        ),
        "w03_term_filter": (
            "select post_id, n_terms, terms from reposts join (select doc_id, count(*) as n_terms, string_agg(term, ',' order by "
            "term) as terms from matched group by 1) using (doc_id)"
        ),
        "w04_term_filter_phrases": (
            "select distinct d.doc_id, p.phrase from (select doc_id, string_split(hyphened, ' ') as w from docs) d, lateral "
            "(select unnest(w) as g union all select array_to_string(w[i:i + 3], ' ') from unnest(range(1, len(w) - 2)) u(i)) g "
            "join (select distinct unnest([term, replace(term, ' ', ''), replace(term, ' ', '-')]) as phrase from phrases where "
            "contains(term, ' ')) p on g.g = p.phrase"
        ),
        "w04b_curated_terms": "select doc_id, term from matched where term not in (select term from ten)",
        "w05_language_share": (
            f"select stage, lang, count(*) as n, {r('count(*) / sum(count(*)) over (partition by stage)')} as share from (select "
            f"'before' as stage, lang from reposts join documents using (doc_id) union all select 'after', lang from reposts join "
            f"documents using (doc_id) where doc_id in (select doc_id from matched)) group by stage, lang"
        ),
        "w06_group_negative_stats": (
            f"select group_id, count(*) as n_posts, count(*) filter (sentiment < 0) as n_negative, "
            f"{r('count(*) filter (sentiment < 0) / count(*)')} as share from grouped group by 1"
        ),
        "w07_top_motives": "select motive, count(*) as n from clipped group by 1 order by n desc, motive limit 5",
        "w07b_place_motives": (
            "select motive, count(*) as n from clipped where category in ('EUROPE', 'ASIA') group by 1 order by n desc, motive "
            "limit 5"
        ),
        "w07c_bounding_box": (
            "select n_nationkey from (select n_nationkey, n_nationkey * 37 % 181 - 90 as lat, n_nationkey * 53 % 361 - 180 as lon "
            "from nation) where lat between -60 and 60 and (lon >= 100 or lon <= -100)"
        ),
        "w08_top_offences": "select offence, count(*) as n from clipped group by 1 order by n desc, offence limit 5",
        "w08b_motive_rollup": "select category, motive, count(*) as n from clipped group by rollup (category, motive)",
        "w10d_posts_text": (
            "select cast(ts as date) as day, lang, count(*) as n, cast(sum(len(text)) as bigint) as chars from events join "
            "documents on event_id % (select count(*) from documents) = doc_id group by 1, 2"
        ),
        "w10b_polarity": (
            "select case when sentiment >= 0.05 then 'positive' when sentiment <= -0.05 then 'negative' else 'neutral' end as "
            "polarity, count(*) as n from posts group by 1"
        ),
        "w11_strong_share": (
            f"select group_id, count(*) as n, {r('avg(case when abs(sentiment) > 0.5 then 1.0 else 0.0 end)')} as strong_share from "
            f"grouped group by 1"
        ),
        "w12_soft_membership": f"select vec_id, topic_id, {r('p')} as p from soft where p >= 0.01",
        "w13_hard_assign": "select vec_id, topic_id from soft qualify row_number() over (partition by vec_id order by p desc, topic_id) = 1",
        "w14_rescue": (
            f"select vec_id, topic_id, {r('p')} as p, best < 0.6 as rescued from (select *, max(p) over (partition by vec_id) as "
            f"best, row_number() over (partition by vec_id order by p desc, topic_id) as k from soft) where (best >= 0.6 and k = 1) "
            f"or (best < 0.6 and p >= 0.01)"
        ),
        "w15_class_tfidf": f"select topic_id, term, {r('weight')} as weight from ranked where rank <= 50",
        "w16_topic_names": "select topic_id, string_agg(term, '_' order by rank) as label from ranked where rank <= 15 group by 1",
        "w17_topic_summary": (
            f"select topic_id, count(distinct post_id) as n_posts, "
            f"{r('count(distinct post_id) / (select count(distinct post_id) from members)')} as share from members group by 1"
        ),
        "w17b_noise_topics": (
            "select topic_id, count(*) as n, count(distinct text) as distinct_texts, count(distinct text) < 0.98 * count(*) as "
            "noise from lab group by 1"
        ),
        "w18_group_summary": (
            "select group_id, count(distinct topic_id) as n_topics, count(distinct post_id) as n_posts from members join grp using "
            "(topic_id) group by 1"
        ),
        "w19_weekly_share_topic": f"select topic_id, week, n, {r('share')} as share from shares",
        "w20_weekly_share_week": f"select topic_id, week, n, {r('n / sum(n) over (partition by week)')} as share from weekly",
        "w20b_heatmap_topics": f"select group_id, topic_id, week, n, {r('share')} as share from heat",
        "w20c_annotated_weeks": (
            "select group_id, topic_id, week, exists (select 1 from calendar c where c.group_id = h.group_id and "
            "cast(date_trunc('week', event_day) as date) = week) as has_event from heat h"
        ),
        "w21_daily_measures": f"select group_id, day, n_posts, {r('mean_score')} as mean_score, {r('strong_share')} as strong_share from daily",
        "w22_rolling_counts": f"select group_id, day, {r('r_posts')} as r_posts, {r('r_incidents')} as r_incidents from focal",
        "w23_rolling_sentiment": f"select group_id, day, {r('r_score')} as r_score, {r('r_incidents')} as r_incidents from focal",
        "w24_rolling_strong": f"select group_id, day, {r('r_strong')} as r_strong, {r('r_incidents')} as r_incidents from focal",
        "w24b_pooled_mean": (
            f"select group_id, day, {r('sum(sum_score) over w / nullif(sum(n_posts) over w, 0)')} as pooled from pdense window w as "
            f"(partition by group_id order by day rows between 29 preceding and current row)"
        ),
        "w24c_rolling_week_stream": (
            f"select group_id, day, "
            f"{r('avg(n) over (partition by group_id order by day rows between 6 preceding and current row)')} as r_incidents from "
            f"(select g.group_id, s.day, coalesce(n, 0) as n from (select distinct cast(user_id % 5 as int) as group_id from events "
            f"where event_type = 'error') g cross join (select cast(d as date) as day from generate_series(date '2024-01-01', date "
            f"'2024-01-30', interval 1 day) t(d)) s left join (select cast(user_id % 5 as int) as group_id, cast(ts as date) as "
            f"day, count(*) as n from events where event_type = 'error' group by all) c on c.group_id = g.group_id and c.day = "
            f"s.day)"
        ),
        "w25_spearman_table": _spearman("select * from long", "value", "r_incidents", "group_id, measure"),
        "w25b_pearson_table": (
            f"select group_id, measure, count(*) as n, {r('corr(value, r_incidents)')} as r from long where value is not null and "
            f"r_incidents is not null group by 1, 2"
        ),
        "w27_lagged_spearman": _spearman((
            "select l.group_id, l.measure, cast(k as int) as lag, l.value, f.y from long l, range(-30, 31) g(k) join (select "
            "group_id, day, round(r_incidents, 9) as y from focal) f on f.group_id = l.group_id and f.day = l.day + cast(k as int)"
        ), "value", "y", "group_id, measure, lag"),
        "w27b_cross_group": _spearman((
            "select a.measure, a.value as x, b.value as y from (select * from long where group_id = 0) a join (select * from long "
            "where group_id = 3) b using (measure, day)"
        ), "x", "y", "measure"),
        "w28_peaks": (
            f"select group_id, measure, day as peak_day, {r('value')} as peak_value from long where value is not null qualify "
            f"row_number() over (partition by group_id, measure order by value desc, day) = 1"
        ),
        "w28b_series_summary": (
            f"select group_id, measure, {r('min(value)')} as low, {r('avg(value)')} as mean, {r('max(value)')} as high, "
            f"{r('max(value) - min(value)')} as span from long where value is not null group by 1, 2"
        ),
        "w28c_decay": (
            "select p.group_id, p.measure, cast(min(l.day - p.day) as int) as days_to_fall from (select * from long where value is "
            "not null qualify row_number() over (partition by group_id, measure order by value desc, day) = 1) p left join long l "
            "on l.group_id = p.group_id and l.measure = p.measure and l.day > p.day and l.value < p.value * 0.5 group by 1, 2"
        ),
        "w28d_event_window": (
            f"select l.group_id, measure, event_day, {r('avg(value) filter (day < event_day)')} as before, "
            f"{r('avg(value) filter (day > event_day)')} as after from long l join calendar c on c.group_id = l.group_id and "
            f"abs(day - event_day) <= 30 group by 1, 2, 3"
        ),
        "w29_kg_nodes": "select node_id, kind from nodes",
        "w29b_kg_node_props": """select node_id, kind, substr(node_id, instr(node_id, ':') + 1) as key, case kind when 'post' then 'author=' || p.author_id || ',day=' || cast(p.day as varchar)
    when 'incident' then 'day=' || cast(k.day as varchar) when 'user' then coalesce('posts=' || u.n, '') when 'topic' then coalesce('groups=' || t.n, '') else '' end as props
    from nodes left join posts p on kind = 'post' and node_id = 'post:' || p.post_id left join keyed k on kind = 'incident' and node_id = 'incident:' || k.incident_id
    left join (select author_id, count(*) as n from posts group by 1) u on node_id = 'user:' || u.author_id left join (select topic_id, count(*) as n from grp group by 1) t on node_id = 'topic:' || t.topic_id""",
        "w30b_thread_edges": (
            "select 'user:' || a.conv_id || ':' || a.role as src, 'user:' || b.conv_id || ':' || b.role as dst, 'replied_to' as "
            "rel, cast(count(*) as double) as weight from conversations a join conversations b on a.conv_id = b.conv_id and b.turn "
            "= a.turn - 1 and a.turn > 0 group by all"
        ),
        "w30c_written_graph": "select rel, count(*) as n, sum(weight) as weight from edges where rel in ('victimized', 'associated_with') group by 1",
        "w30d_dated_edges": """select rel, cast(date_trunc('month', coalesce(p.day, k.day)) as date) as month, count(*) as n from edges
    left join posts p on rel in ('tweeted', 'tweeted_on', 'in_topic', 'has_hashtag') and case rel when 'tweeted' then dst else src end = 'post:' || p.post_id
    left join keyed k on rel in ('occurred_on', 'victimized') and src = 'incident:' || k.incident_id group by 1, 2""",
        "w34d_subgraph_period": (
            "select 'in_topic' as rel, count(*) as n from members join g0 using (topic_id) join posts using (post_id) where day "
            "between date '1996-01-01' and date '1996-03-31' union all select 'tweeted', count(*) from grouped where group_id = 0 "
            "and day between date '1996-01-01' and date '1996-03-31'"
        ),
        "w30_kg_edges": f"select src, dst, rel, {r('weight')} as weight from edges",
        "w31_kg_stats": (
            "select 'node' as part, kind as name, count(*) as n from nodes group by rollup (kind) union all select 'edge', rel, "
            "count(*) from edges group by rollup (rel)"
        ),
        "w31b_kg_checks": (
            "select 'endpoints' as \"check\", (select count(*) from (select src as x from edges union all select dst from edges) "
            "where x not in (select node_id from nodes)) as violations union all select 'posts', abs(count(*) filter (rel = "
            "'tweeted') - count(*) filter (rel = 'tweeted_on')) from edges union all select 'incidents', abs(count(*) filter (rel "
            "= 'occurred_on') - count(*) filter (rel = 'victimized')) from edges"
        ),
        "w32_kg_mean_topics": f"select {r('count(*) filter (rel = $$in_topic$$) / count(*) filter (rel = $$tweeted$$)')} as mean_topics from edges",
        "w33_date_bridge": (
            "select day, group_id, n_posts, n_incidents from (select day, group_id, count(*) as n_posts from grouped group by all) "
            "join (select day, group_id, count(*) as n_incidents from keyed group by all) using (day, group_id)"
        ),
        "w34_match_path": (
            "select author_id as user_id, group_id, count(*) as paths from posts join members using (post_id) join grp using "
            "(topic_id) group by all"
        ),
        "w34b_subgraph": (
            "select 'in_topic' as rel, count(*) as n from members join g0 using (topic_id) where post_id in (select post_id from "
            "posts) union all select 'tweeted', count(*) from grouped where group_id = 0"
        ),
        "w34c_cluster_profile": (
            f"select topic_id, count(distinct post_id) as n_posts, {r('avg(sentiment)')} as mean_score from posts join members "
            f"using (post_id) where author_id in (select author_id from posts group by 1 having count(*) >= 15) group by 1"
        ),
        "w35_snapshots": (
            "select period, least(a, b) as src, greatest(a, b) as dst, sum(w) as weight from (select distinct "
            "cast(date_trunc('month', day) as date) as period, 'user:' || author_id as a, 'post:' || post_id as b, 1.0::double as "
            "w from members join g0 using (topic_id) join posts using (post_id) where day between date '1996-01-01' and date "
            "'1996-06-30' union all select cast(date_trunc('month', day) as date), 'post:' || post_id, 'topic:' || topic_id, 1.0 "
            "from members join g0 using (topic_id) join posts using (post_id) where day between date '1996-01-01' and date "
            "'1996-06-30') group by all"
        ),
        "w35c_snapshots_replies": """select period, least(a, b) as src, greatest(a, b) as dst, sum(w) as weight from (
    select distinct period, 'user:' || author_id as a, 'post:' || post_id as b, 1.0::double as w from half
    union all select period, 'post:' || post_id, 'topic:' || topic_id, 1.0 from half
    union all select period, 'user:' || o_custkey, 'user:' || before, 1.0 from (select distinct period, post_id from half)
        join (select o_orderkey as post_id, o_custkey, lag(o_custkey) over (partition by o_orderdate, o_orderpriority order by o_orderkey) as before from orders) using (post_id) where before <> o_custkey) group by all""",
        "w35b_snapshots_stream": "select period, src, dst, weight from snapstream",
        "w38_modularity_given_labels": (
            f"select period, {r('ins / m - d2 / (4 * m * m)')} as modularity from (select period, sum(weight) as m, sum(case when "
            f"a.community = b.community then weight else 0 end) as ins from snapyear s join given a using (period) join given b "
            f"using (period) where a.node = src and b.node = dst group by 1) join (select period, sum(d * d) as d2 from (select "
            f"period, community, sum(weight) as d from (select period, src as node, weight from snapyear union all select period, "
            f"dst, weight from snapyear) join given using (period, node) group by all) group by 1) using (period)"
        ),
        "w39_jaccard_links": _links("domgroup", 3, 0.01),
        "w39b_jaccard_links_month": _links("domtopic", 1, 0.05),
        "w40_evolution_types": f"""select period, community, unnest(list_filter([case when back = 0 and period > (select min(period) from domtopic) then 'birth' end, case when ahead = 0 and period < (select max(period) from domtopic) then 'death' end, case when ahead > 1 then 'split' end, case when back > 1 then 'merge' end, case when back <= 1 and ahead = 1 then 'continue' end], lambda e: e is not null)) as event
from (select n.period, n.community, (select count(*) from ({_links("domtopic", 1, 0.08)}) l where l.period = n.period and l.a = n.community) as ahead, (select count(*) from ({_links("domtopic", 1, 0.08)}) l where cast(l.period + interval 1 month as date) = n.period and l.b = n.community) as back from (select distinct period, community from domtopic) n)""",
        "w41_community_sentiment": (
            f"select period, community, count(*) as size, {r('avg(m)')} as mean_score from domgroup join (select author_id as "
            f"user_id, avg(sentiment) as m from posts group by 1) using (user_id) group by 1, 2"
        ),
        "w42_active_users": "select user_id, n_posts from active",
        "w43_user_profiles": (
            f"select author_id as user_id, topic_id, {r('sum(round(p * 1e6)) / 1e6')} as s from posts join members using (post_id) "
            f"where author_id in (select user_id from active) group by all"
        ),
        "w44_pair_weights": (
            f"select group_id, a, b, {r('w')} as weight from (select a.group_id, a.user_id as a, b.user_id as b, sum(a.s * b.s) as "
            f"w from bygroup a join bygroup b on a.group_id = b.group_id and a.topic_id = b.topic_id and a.user_id < "
            f"b.user_id group by all)"
        ),
        "w45_pair_weights_naive": (
            f"select a.author_id as a, b.author_id as b, {r('sum(a.p * b.p)')} as weight from (select author_id, topic_id, p from "
            f"posts join members using (post_id) where author_id in (select user_id from active)) a join (select author_id, "
            f"topic_id, p from posts join members using (post_id) where author_id in (select user_id from active)) b on a.topic_id "
            f"= b.topic_id and a.author_id < b.author_id group by 1, 2"
        ),
        "w45c_no_activity_floor": (
            f"select group_id, user_id, {r('sum(s * (t - s))')} as degree from everyone join (select group_id, topic_id, sum(s) as "
            f"t from everyone group by all) using (group_id, topic_id) group by all"
        ),
        "w46_weighted_degree": (
            f"select group_id, user_id, {r('sum(s * (t - s))')} as degree from restricted join (select group_id, topic_id, sum(s) "
            f"as t from restricted group by all) using (group_id, topic_id) group by all"
        ),
        "w47_eigen_centrality": f"select group_id, user_id, {r('x')} as centrality from x{STEPS}",
        "w47b_eigen_converged": f"select group_id, user_id, {r('x')} as centrality from x{SETTLED}",
        "w47c_eigen_residual": "select distinct group_id, true as settled from restricted",
        "w48_influence_top5": (
            f"select group_id, rank, {r('centrality')} as centrality, followers, n_posts, {r('score')} as score, {r('influence')} "
            f"as influence from top"
        ),
        "w48b_rank_overlap": " union all ".join((
            f"select '{c}' as ranking, group_id, "
            f"{r('count(*) filter (user_id in (select user_id from (select *, row_number() over (partition by group_id order by ' + c + ' desc, user_id) as k from inf) z where k <= 5 and z.group_id = top.group_id)) / 5')} "
            f"as overlap from top group by 2"
        ) for c in ("centrality", "followers", "n_posts")),
        "w49_influence_bins": f"select group_id, {r('bin_lo')} as bin_lo, n, {r('mean')} as mean, {r('se')} as se, is_peak from bins",
        "w49b_group_contrast": (
            f"select group_id, {r('avg(centrality)')} as mean_centrality, {r('avg(followers)')} as mean_followers, "
            f"{r('avg(n_posts)')} as mean_posts, {r('avg(score)')} as mean_score, {r('avg(influence)')} as mean_influence, "
            f"{r('any_value(mse)')} as mean_se from top join (select group_id, avg(se) as mse from bins group by 1) using "
            f"(group_id) group by 1"
        ),
        "w50_toxic_precision_recall": (
            f"select lang, tp, fp, fn, {r('tp / nullif(tp + fp, 0)')} as precision, {r('tp / nullif(tp + fn, 0)')} as recall, "
            f"{r('2 * tp / nullif(2 * tp + fp + fn, 0)')} as f1 from (select lang, count(*) filter (hit and toxic = 1) as tp, "
            f"count(*) filter (hit and toxic = 0) as fp, count(*) filter (not hit and toxic = 1) as fn from (select lang, toxic, "
            f"doc_id in (select doc_id from (select doc_id, unnest(w) as term from tokens) join ten using (term)) as hit from "
            f"labels join documents using (doc_id)) group by 1)"
        ),
        "w51_stream_daily_counts": "select cast(ts as date) as day, event_type, count(*) as n from events group by all",
        "w53_corpus_stats": (
            "select 'posts' as measure, count(*) as n from posts union all select 'authors', count(distinct author_id) from posts "
            "union all select 'days', count(distinct day) from posts union all select 'memberships', count(*) from members union "
            "all select 'topics', count(distinct topic_id) from members"
        ),
        "w54_distributed_rank": (
            "select distinct o_totalprice as price, rank() over (order by o_totalprice) + (count(*) over (partition by "
            "o_totalprice) - 1) / 2.0 as rank from orders"
        ),
    }
    sql["w45b_pair_weights_factorised"] = sql["w45_pair_weights_naive"]
    raw = sql["w25_spearman_table"].replace("round(case", "(case").replace("end, 6) + 0.0 as r_s", "end) as r_s")
    sql["w26_spearman_p"] = _with_p(raw)
    out = {name: with_views(text) for name, text in sql.items()}
    links = _links("domgroup", 3, 0.2)
    chain = (
        f"select distinct period, community, 1 as length from domgroup union select cast(c.period + interval 3 month as date), "
        f"l.b, c.length + 1 from chain c join links l on l.period = c.period and l.a = c.community"
    )
    body = with_views("select * from domgroup").removesuffix(" select * from domgroup").replace("with ", "with recursive ", 1)
    out["w40b_lifespans"] = (
        f"{body}, links as materialized ({links}), chain as ({chain}) select period, community, max(length) as length from "
        f"chain group by 1, 2"
    )
    out["w09_sentiment_rules"], out["w10_sentiment_plain"] = _sentiment(True), _sentiment(False)
    clean = "trim(regexp_replace(regexp_replace(lower(text), '[^\\p{L}\\p{N}\\s]', '', 'g'), '\\s+', ' ', 'g'))"
    out["w09b_sentiment_clean"] = _sentiment(True).replace("text as body", f"{clean} as body")
    out["w10c_sentiment_arrow"] = out["w10_sentiment_plain"]
    snap = with_views("select * from snapstream")
    out["w36_components"] = (
        f"with recursive e as ({snap}), reach as (select distinct period, src as node, src as other from e union select "
        f"distinct period, dst, dst from e union select r.period, r.node, case when e.src = r.other then e.dst else e.src end "
        f"from reach r join e on e.period = r.period and (e.src = r.other or e.dst = r.other)) select period, node, min(other) "
        f"as label from reach group by 1, 2"
    )
    return out


def _links(users: str, months: int, gamma: float) -> str:
    return (
        f"select period, a, b, common, round(common / (sa + sb - common), 6) + 0.0 as jaccard from (select x.period, "
        f"x.community as a, y.community as b, count(*) as common, any_value(x.n) as sa, any_value(y.n) as sb from (select *, "
        f"count(*) over (partition by period, community) as n from {users}) x join (select *, count(*) over (partition by "
        f"period, community) as n from {users}) y on x.user_id = y.user_id and y.period = cast(x.period + interval {months} "
        f"month as date) group by 1, 2, 3) where common / (sa + sb - common) >= {gamma}"
    )
