"""DuckDB SQL of the queries: the city from the raw tables, then each method by brute force."""

CITY = """with recursive
buy as (select o_custkey as usr, l_partkey as poi, l_shipdate as d, l_orderkey as o, l_linenumber as ln, l_returnflag as rf
    from lineitem join orders on l_orderkey = o_orderkey),
side as (select ceil(sqrt(count(*)))::BIGINT as side from customer),
step as (
    select c_custkey as v, c_custkey + 1 as t, c_acctbal as bal from customer, side where c_custkey % side <> side - 1
    union all select c_custkey, c_custkey + side, c_acctbal from customer, side where c_custkey % side = 0 or c_custkey % 4 <> 3),
one_way as (select v as src, t as dst, (1 + floor(abs(bal - c_acctbal) / 500))::BIGINT as len from step join customer on c_custkey = t),
road as (select src, dst, len from one_way union all select dst, src, len from one_way),
users as (select c_custkey as usr, c_custkey as v, (1 + c_nationkey % 3)::BIGINT as dis from customer),
opened as (select poi, usr, row_number() over (partition by poi order by d, o, ln, usr) as nth from buy),
sites as (select poi, usr as v, (1 + p_size % 5)::BIGINT as dis from opened join part on p_partkey = poi where nth = 1),
words as (select p_partkey as poi, unnest(list_concat(string_split(p_name, ' '), [lower(p_type), lower(p_brand)])) as term from part),
raw_terms as (select poi, term, count(*)::BIGINT as tf from words group by poi, term),
n_sites as (select count(distinct poi) as n from raw_terms),
idf as (select term, round(1000 * ln(1 + any_value(n) / count(*)))::BIGINT as idf_m from raw_terms, n_sites group by term),
norms as (select poi, sum(tf * idf_m * tf * idf_m)::BIGINT as norm2 from raw_terms join idf using (term) group by poi),
site_terms as (select poi, term, tf, idf_m, round(1000000::DOUBLE * (tf * idf_m) / sqrt(norm2))::BIGINT as w_m
    from raw_terms join idf using (term) join norms using (poi)),
fame as (select usr, term, sum(tf)::BIGINT * any_value(idf_m) * any_value(idf_m) as fame from buy join site_terms using (poi) group by usr, term),
user_terms as (select usr, term from (select usr, term, row_number() over (partition by usr order by fame desc, term) as nth from fame) where nth <= 3),
checkins as (select distinct poi, usr from buy where rf = 'R'),
following as (select usr, lead(usr) over w as dst, date_diff('day', d::DATE, (lead(d) over w)::DATE) as gap from buy window w as (partition by poi order by d, o, ln, usr)),
follows as (select distinct usr as src, dst from following join customer on c_custkey = usr where dst is not null and dst <> usr
    and gap <= case when c_acctbal >= 9500 then 365 when c_acctbal >= 8000 then 90 else 7 end),
social as (select src, dst, (count(*) over (partition by dst))::BIGINT as indeg from follows),
friends as (select src as usr, dst as friend from follows union select dst, src from follows)
"""

GAIN = """, n_friends as (select usr, count(*) as n from friends group by usr),
text_sim as (select usr, poi, sum(w_m)::BIGINT as text_m from user_terms join site_terms using (term) group by usr, poi),
visits as (select f.usr, c.poi, count(*)::BIGINT as visits from friends f join checkins c on f.friend = c.usr group by f.usr, c.poi),
shared as (select usr, poi, visits / n as social from visits join n_friends using (usr)),
gains as (select coalesce(t.usr, s.usr) as usr, coalesce(t.poi, s.poi) as poi,
    {a}::DOUBLE * coalesce(social, 0::DOUBLE) + {b}::DOUBLE * (coalesce(text_m, 0) / 1000000::DOUBLE) as gain
    from text_sim t full join shared s on t.usr = s.usr and t.poi = s.poi)
"""

CAND = """, cand as (select poi from sites order by md5('c|' || poi), poi limit {n})
"""

DIST = """, dist(src, v, d) using key (src, v) as (
    select distinct v, v, 0::BIGINT from {sources}
    union
    select x.src, r.dst, min(x.d + r.len)::BIGINT from dist x join road r on x.v = r.src left join recurring.dist old on old.src = x.src and old.v = r.dst
    where x.d + r.len < coalesce(old.d, 1000000000000) group by x.src, r.dst)
"""

TOPK = """, scored as (select g.usr, g.poi, gain / greatest(u.dis + d.d + s.dis, 1::DOUBLE) as score
    from gains g join users u on u.usr = g.usr join sites s on s.poi = g.poi join dist d on d.src = s.v and d.v = u.v where gain > 0),
topk as (select usr, poi, score, rnk from (select *, row_number() over (partition by usr order by score desc, poi)::INT as rnk from scored) where rnk <= {k})
"""

MEMBER = """, placed as (select distinct src as v from road),
grid as (select v, v % ceil(sqrt((select count(*) from placed)))::BIGINT as x, v // ceil(sqrt((select count(*) from placed)))::BIGINT as y from placed)
"""


def member(depth: int) -> str:
    out, at = MEMBER, "(select v, x, y, '' as leaf from grid)"
    for i in range(depth):
        out += f", half{i} as (select *, ntile(2) over (partition by leaf order by x, v) - 1 as h from {at}), split{i} as (select v, x, y, leaf || (2 * h + ntile(2) over (partition by leaf, h order by y, v) - 1)::BIGINT as leaf from half{i})\n"
        at = f"split{i}"
    return out + f", member as (select v, leaf from {at}), levels as (select unnest(range(0, {depth} + 1)) as level)\n"


def two_hop(sets: str) -> str:
    """Exact two-hop influence of the (set_id, usr) rows of ``sets``."""
    return f""", seeds as (select distinct set_id, usr as x from {sets}),
hop as (select set_id, dst as x, 1 - product(1 - 1 / indeg::DOUBLE) as p1 from seeds join social on src = x group by set_id, dst),
near as (select set_id, x, 1::DOUBLE as p1 from seeds union all select h.set_id, h.x, p1 from hop h where not exists (select 1 from seeds s where s.set_id = h.set_id and s.x = h.x)),
reach as (select set_id, dst as x, 1 - product(1 - p1 / indeg) as p2 from near join social on src = x group by set_id, dst),
beyond as (select r.set_id, sum(p2) as more from reach r where not exists (select 1 from seeds s where s.set_id = r.set_id and s.x = r.x) group by r.set_id),
reached as (select s.set_id, round(any_value(s.own) + coalesce(any_value(more), 0), 6) as influence
    from (select set_id, count(*) as own from seeds group by set_id) s left join beyond b on b.set_id = s.set_id group by s.set_id)
"""


def coin(text: str) -> str:
    return f"('0x' || substr(md5({text}), 1, 8))::BIGINT"


#: Everyone whom some candidate's audience may reach.
UNIVERSE = """, act as (select usr from aud union select s.dst from act a join social s on s.src = a.usr), uni as (select usr, row_number() over (order by usr) - 1 as place, count(*) over () as n from act),
scale as (select count(*)::DOUBLE as n, 1 / greatest(count(*), 2)::DOUBLE as delta from act)
"""

#: Candidates alone (p = q) and in pairs, with their exact two-hop influence.
SETS = (
    ", sets_ as (select poi as p, poi as q, poi as set_id from cand union all select a.poi, b.poi, 1000000 * a.poi + b.poi from cand a join cand b on a.poi < b.poi), both_ as (select set_id, usr from sets_ join aud on aud.poi in (p, q))\n"
    + two_hop("both_")
    + ", local_ as (select p, q, set_id, coalesce(influence, 0)::DOUBLE as local from sets_ left join reached using (set_id))\n"
)


def samples(size: str, universe: str = "uni") -> str:
    """Two collections (r = 0, 1) of ``size`` reverse samples, from the first ids that the solvers use; hit(r, rid, poi, depth)."""
    return f""", ids as (select r, (r + 1) * 1099511627776 + i as rid from (select unnest([0, 1]) as r), (select unnest(range(0, 1000)) as i), {size} where i < size),
start as (select r, rid, usr as target from ids join {universe} on place = {coin("concat_ws('|', rid, 't', 1)")} % n),
back as (select rid, src, dst from ids, social where {coin("concat_ws('|', rid, src, dst, 1)")} * indeg < 4294967296),
walk as (select rid, target as usr, 0 as depth from start union select w.rid, b.src, w.depth + 1 from walk w join back b on b.rid = w.rid and b.dst = w.usr where w.depth < 60),
step_of as (select rid, usr, min(depth) as depth from walk group by rid, usr),
hit as (select r, rid, poi, min(depth) as depth from step_of join aud using (usr) join ids using (rid) group by r, rid, poi)
"""


#: What each set covers in each collection: any, exclusively far, far at all.
COVERED = """, cov as (select r, set_id, count(*) as any_, count(*) filter (f = 1 and n = 0) as excl, count(*) filter (f = 1) as incl
    from (select r, set_id, rid, max((depth > 2)::INT) as f, max((depth <= 2)::INT) as n from sets_ join hit on poi in (p, q) group by r, set_id, rid) group by r, set_id),
known as (select r, p, q, set_id, local, coalesce(any_, 0) as any_, coalesce(excl, 0) as excl, coalesce(incl, 0) as incl from local_ cross join (select unnest([0, 1]) as r) left join cov using (r, set_id))
"""


def greedy2(name: str, value: str) -> str:
    """The greedy pair by an expression over ``known`` in the first collection: name(p, q, set_id)."""
    return f""", {name}_1 as (select p as one from known where r = 0 and p = q order by round({value}, 9) desc, p limit 1),
{name} as (select k.p, k.q, k.set_id from known k, {name}_1 where r = 0 and p <> q and one in (p, q) order by round({value}, 9) desc, case when p = one then q else p end limit 1)
"""


def cap2(name: str, where: str) -> str:
    """A bound on what two sites cover in the first collection, from a greedy trace over the hits ``where``: name(cap, ratio)."""
    return f""", {name}_0 as (select distinct rid, poi from hit where r = 0 and {where}),
{name}_a as (select poi, count(*) as n from {name}_0 group by poi), {name}_a1 as (select poi, n from {name}_a order by n desc, poi limit 1),
{name}_r1 as (select * from {name}_0 where rid not in (select rid from {name}_0 where poi in (select poi from {name}_a1))),
{name}_b as (select poi, count(*) as n from {name}_r1 group by poi), {name}_b1 as (select poi, n from {name}_b order by n desc, poi limit 1),
{name}_r2 as (select * from {name}_r1 where rid not in (select rid from {name}_r1 where poi in (select poi from {name}_b1))),
{name}_c as (select poi, count(*) as n from {name}_r2 group by poi),
{name}_s as (select coalesce((select n from {name}_a1), 0) as one, coalesce((select n from {name}_b1), 0) as two, coalesce((select sum(n) from (select n from {name}_a order by n desc limit 2)), 0) as top0,
    coalesce((select sum(n) from (select n from {name}_b order by n desc limit 2)), 0) as top1, coalesce((select sum(n) from (select n from {name}_c order by n desc limit 2)), 0) as top2),
{name} as (select least(top0, one + top1, one + two + top2)::DOUBLE as cap, (one + two) / (1 - exp(-1)) as ratio from {name}_s)
"""


def lower(covered: str, n: str, size: str, a: str) -> str:
    return f"greatest(0, {n} / {size} * (pow(sqrt({covered} + 2 * {a} / 9) - sqrt({a} / 2), 2) - {a} / 18))"


def upper(cap: str, n: str, size: str, a: str) -> str:
    return f"{n} / {size} * pow(sqrt({cap} + {a} / 2) + sqrt({a} / 2), 2)"

_WEIGHTS = CITY[CITY.index("raw_terms as") : CITY.index("fame as")]

#: The text-rich city of events, documents, conversations and vectors.
CITY_B = (
    """with recursive
ev as (select event_id, ts, user_id, event_type, json_extract(props, '$.k')::BIGINT as k from events),
n_vec as (select count(*)::BIGINT as n_vec from embeddings), n_conv as (select max(conv_id) + 1 as n_conv from conversations),
usr_ as (select distinct user_id as usr from ev),
users as (select usr, usr % n_vec as v, 1::BIGINT as dis from usr_, n_vec),
docs_ as (select doc_id, text from documents where doc_id < 100),
sites as (select doc_id as poi, doc_id % n_vec as v, 1::BIGINT as dis from docs_, n_vec),
words as (select doc_id as poi, unnest(regexp_extract_all(lower(text), '\\p{L}+')) as term from docs_),
"""
    + _WEIGHTS
    + """said as (select conv_id, unnest(regexp_extract_all(lower(text), '\\p{L}+')) as term from conversations where role = 'user'),
user_terms as (select distinct usr, term from usr_ cross join n_conv join said on said.conv_id = usr % n_conv),
gaps as (select a.vec_id as src, b.vec_id as dst, sqrt(list_reduce(list_prepend(0::DOUBLE, list_transform(list_zip(a.embedding, b.embedding), lambda x: ((x[1] - x[2]) * (x[1] - x[2]))::DOUBLE)), lambda p, q: p + q)) as gap
    from embeddings a, embeddings b where a.vec_id <> b.vec_id),
one_way as (select src, dst, ceil(100 * gap)::BIGINT as len from (select *, row_number() over (partition by src order by gap, dst) as nth from gaps) where nth <= 4 or dst = src + 1),
road as (select src, dst, min(len)::BIGINT as len from (select src, dst, len from one_way union all select dst, src, len from one_way) group by src, dst),
checkins as (select distinct k as poi, user_id as usr from ev where event_type = 'purchase'),
follows as (select distinct src, dst from (select user_id as src, lead(user_id) over w as dst, (epoch_us(lead(ts) over w) - epoch_us(ts)) / 1000000 as gap from ev window w as (partition by k order by ts, event_id))
    where dst is not null and dst <> src and gap <= 3600 * 10000.0::DOUBLE / (select count(*) from ev)),
social as (select src, dst, (count(*) over (partition by dst))::BIGINT as indeg from follows),
friends as (select src as usr, dst as friend from follows union select dst, src from follows)
"""
)
