"""DuckDB SQL for graphs and programs, from the same tables."""

from __future__ import annotations

_NEXT = "where dst is not null and src <> dst group by src, dst"
#: CTEs that define e(src, dst, weight) and v(id) of each graph.
GRAPHS = {
    "part_next": f"""n as (select l_partkey as src, lead(l_partkey) over (partition by l_orderkey order by l_linenumber, l_partkey) as dst from lineitem),
        e as materialized (select src, dst, count(*)::bigint as weight from n {_NEXT}), v as (select p_partkey as id from part)""",
    "word_next": r"""w as (select doc_id, unnest(regexp_extract_all(lower(text), '\p{L}+')) as word, generate_subscripts(regexp_extract_all(lower(text), '\p{L}+'), 1) as pos from documents),
        wp as (select word as a, lead(word) over (partition by doc_id order by pos) as b from w),
        wc as materialized (select a, b, count(*)::bigint as weight from wp where b is not null and a <> b group by a, b),
        ids as materialized (select key, row_number() over (order by key) - 1 as id from (select a as key from wc union select b from wc)),
        e as materialized (select x.id as src, y.id as dst, weight from wc join ids x on a = x.key join ids y on b = y.key), v as (select id from ids)""",
    "event_chain": """n as (select event_id as src, lead(event_id) over (partition by user_id order by ts, event_id) as dst from events),
        e as materialized (select src, dst, 1::bigint as weight from n where dst is not null), v as (select event_id as id from events)""",
    "user_next": f"""u as (select user_id as key, row_number() over (order by user_id) - 1 as id from (select distinct user_id from events)),
        n as (select a.id as src, b.id as dst from events x join events y on y.event_id = x.event_id + 1 join u a on a.key = x.user_id join u b on b.key = y.user_id),
        e as materialized (select src, dst, count(*)::bigint as weight from n {_NEXT}), v as (select id from u)""",
    "cust_part": f"""o as (select count(*) as off from customer), n as (select o_custkey as src, l_partkey + off as dst from orders join lineitem on o_orderkey = l_orderkey, o),
        e as materialized (select src, dst, count(*)::bigint as weight from n {_NEXT}), v as (select c_custkey as id from customer union all select p_partkey + off from part, o)""",
    "supp_part": f"""o as (select count(*) as off from supplier), n as (select l_suppkey as src, l_partkey + off as dst from lineitem, o),
        e as materialized (select src, dst, count(*)::bigint as weight from n {_NEXT}), v as (select s_suppkey as id from supplier union all select p_partkey + off from part, o)""",
    "page_link": f"""h as (select url, regexp_extract(url, '^(https?://[^/]+)', 1) as host, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) as href from pages),
        l as (select url, case when regexp_matches(href, '^https?://') then href when starts_with(href, '/') then host || href else host || '/' || href end as target from h),
        ids as (select key, row_number() over (order by key) - 1 as id from (select url as key from pages union select target from l)),
        n as (select a.id as src, b.id as dst from l join ids a on a.key = url join ids b on b.key = target),
        e as materialized (select src, dst, count(*)::bigint as weight from n {_NEXT}), v as (select id from ids)""",
    "geo_tree": """o as (select (select count(*) from region) as nr, (select count(*) from nation) as nn, (select count(*) from customer) as nc),
        e as materialized (select n_regionkey::bigint as src, nr + n_nationkey as dst, 1::bigint as weight from nation, o union all select nr + c_nationkey, nr + nn + c_custkey, 1 from customer, o
            union all select nr + s_nationkey, nr + nn + nc + s_suppkey, 1 from supplier, o), v as (select r_regionkey::bigint as id from region union all select dst from e)""",
    "turn_chain": """t as (select conv_id, turn, row_number() over (order by conv_id, turn) - 1 as id from (select distinct conv_id, turn from conversations)),
        n as (select id as src, lead(id) over (partition by conv_id order by turn) as dst from t), e as materialized (select src, dst, 1::bigint as weight from n where dst is not null), v as (select id from t)""",
    "doc_dup": """l as (select doc_id, lower(trim(unnest(string_split(text, chr(10))))) as line from documents), k as (select line, min(doc_id) as src from l where length(line) >= 40 group by line),
        e as materialized (select distinct src, doc_id as dst, 1::bigint as weight from l join k using (line) where doc_id <> src), v as (select doc_id as id from documents)""",
    "vec_knn": """x as (select vec_id, label, embedding::double[] as e from embeddings where label is not null),
        e as materialized (select a.vec_id as src, b.vec_id as dst, 1::bigint as weight from x a join x b on a.label = b.label and a.vec_id < b.vec_id and list_cosine_similarity(a.e, b.e) >= 0.4), v as (select vec_id as id from embeddings)""",
}
DEGREES = """di as (select dst as id, count(*) as d from e group by dst), dо as (select src as id, count(*) as d from e group by src),
    deg as materialized (select v.id, coalesce(di.d, 0)::bigint as in_deg, coalesce(dо.d, 0)::bigint as out_deg from v left join di on di.id = v.id left join dо on dо.id = v.id)""".replace("dо", "dout")
SYMMETRIC = "s as materialized (select src, dst, min(weight)::bigint as weight from (select src, dst, weight from e union all select dst, src, weight from e) group by src, dst)"


def head(g: str, *more: str) -> str:
    return "with recursive " + ",\n".join([GRAPHS[g], *more])


def stats(g: str) -> str:
    return head(g, DEGREES) + " select count(*) as v, sum(in_deg)::bigint as e, round(sum(in_deg)::double / count(*), 6) as avg_deg, max(in_deg) as max_in, max(out_deg) as max_out, sum(in_deg)::bigint * 8 as raw_bytes from deg"


def histogram(g: str, side: str) -> str:
    return head(g, DEGREES) + f" select {side}_deg as deg, count(*) as vertices from deg group by 1"


def intervals(g: str, shards: int) -> str:
    """Starts of the greedy cut: the least id after a start whose running in-degree passes the start's base by more than the threshold."""
    return head(
        g,
        DEGREES,
        f"t as (select greatest(1, sum(in_deg)::bigint // {shards}) as threshold, max(id) as last from deg)",
        "p as materialized (select id, in_deg, sum(in_deg) over (order by id)::bigint as upto from deg)",
        "cuts as (select 0::bigint as lo, 0::bigint as base union all select x.id, x.upto - x.in_deg from (select (select min(p.id) from p, t where p.id > cuts.lo and p.upto > cuts.base + t.threshold) as nid from cuts) k join p x on x.id = k.nid)",
        "iv as materialized (select (row_number() over (order by lo) - 1)::int as shard_id, lo, coalesce(lead(lo) over (order by lo) - 1, (select last from t)) as hi from cuts)",
    )


def pagerank(g: str, rounds: int = 10, damping: float = 0.85, weighted: bool = False, seeds: tuple[int, ...] = ()) -> str:
    share = "value * weight / total" if weighted else "value / out_deg"
    out = "join (select src, sum(weight) as total from e group by src) t on t.src = e.src" if weighted else "join deg on deg.id = e.src"
    restart = f"case when v.id in {seeds!r} then {(1 - damping) / len(seeds)!r}::double else 0 end" if seeds else f"{1 - damping!r}::double / n"
    parts = [DEGREES, "nv as (select count(*)::double as n from v)", "r0 as materialized (select id, 1.0::double / n as value from v, nv)"]
    for k in range(1, rounds + 1):
        parts.append(f"r{k} as materialized (select v.id, {restart} + {damping!r}::double * coalesce(m.s, 0) as value from v cross join nv left join (select dst, sum({share}) as s from e join r{k - 1} r on r.id = e.src {out} group by dst) m on m.dst = v.id)")
    return head(g, *parts)


def influence(g: str, rounds: int, damping: float = 0.5) -> str:
    parts = ["r0 as materialized (select id, 1.0::double as value from v)"]
    for k in range(1, rounds + 1):
        parts.append(f"r{k} as materialized (select v.id, 1.0::double + {damping!r}::double * coalesce(m.s, 0) as value from v left join (select dst, sum(value) as s from e join r{k - 1} r on r.id = e.src group by dst) m on m.dst = v.id)")
    return head(g, *parts)


def hits(g: str, rounds: int) -> str:
    parts = ["h0 as materialized (select id, 1.0::double as hub, 1.0::double as authority from v)"]
    for k in range(1, rounds + 1):
        parts += [
            f"x{k} as materialized (select v.id, coalesce(sum(hub), 0) as a from v left join e on e.dst = v.id left join h{k - 1} h on h.id = e.src group by v.id)",
            f"a{k} as materialized (select id, a / sqrt(sum(a * a) over ()) as authority from x{k})",
            f"y{k} as materialized (select v.id, coalesce(sum(authority), 0) as b from v left join e on e.src = v.id left join a{k} a on a.id = e.dst group by v.id)",
            f"h{k} as materialized (select y.id, b / sqrt(sum(b * b) over ()) as hub, authority from y{k} y join a{k} a on a.id = y.id)",
        ]
    return head(g, *parts)


def visits(g: str, shards: int) -> str:
    """k(iter, shards_read): shards with an in-edge from a vertex that the round before reached, by rounds of unit-weight distances."""
    cut = intervals(g, shards)[len("with recursive ") :]
    reach = sssp(g, False)[len("with recursive ") + len(GRAPHS[g]) :]
    return "with recursive " + cut + reach + """, held as materialized (select distinct shard_id, src from e join iv on dst between lo and hi),
        k as materialized (select (value + 1)::int as iter, count(distinct shard_id) as shards_read from dist left join held on src = dist.id where value is not null group by 1)"""


def sssp(g: str, weighted: bool = True, source: int | str = 0) -> str:
    step = "e.weight" if weighted else "1"
    return head(g) + f""", d(id, dist) using key (id) as (select {source}::bigint, 0::bigint union
        (select e.dst, min(d.dist + {step})::bigint from d join e on e.src = d.id left join recurring.d r on r.id = e.dst where r.dist is null or d.dist + {step} < r.dist group by e.dst)),
        dist as (select v.id, d.dist as value from v left join d on d.id = v.id) """


def components(g: str) -> str:
    return head(g, SYMMETRIC) + """, c(id, label) using key (id) as (select id, id from v union
        (select s.dst, min(c.label) from c join s on s.src = c.id join recurring.c r on r.id = s.dst where c.label < r.label group by s.dst)) """


def label_rounds(g: str, rounds: int) -> str:
    """(iter, active): vertices whose least label the round before changed, all at first, for as many rounds as there are such."""
    parts = ["l0 as materialized (select id, id as label from v)"]
    counts = ["select 1 as iter, count(*) as active from v"]
    for k in range(1, rounds + 1):
        parts.append(f"l{k} as materialized (select p.id, least(p.label, coalesce(min(q.label), p.label)) as label, p.label as old from l{k - 1} p left join s on s.dst = p.id left join l{k - 1} q on q.id = s.src group by p.id, p.label)")
        counts.append(f"select {k + 1}, count(*) filter (label <> old) from l{k}")
    return head(g, SYMMETRIC, *parts) + " select iter::int as iter, active from (" + " union all ".join(counts) + ") where active > 0"
