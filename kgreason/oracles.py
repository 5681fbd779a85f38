"""DuckDB SQL for the registered queries, in fixed numbers."""

from __future__ import annotations

from .ids import CODES, OFFSETS, SPAN
from .plans.query import ThreeHopQuery

UNIT = 4194304


def _dense(table: str, key: str, column: str) -> str:
    return f"(select {key}, dense_rank() over (order by {column}) - 1 as k from {table} where {column} is not null)"


_ORDER_LINES = "orders join lineitem on o_orderkey = l_orderkey"
_TOKENS = "(select doc_id, dense_rank() over (order by token) - 1 as k from (select distinct doc_id, unnest(regexp_extract_all(lower(text), '[a-z]+')) as token from documents))"
_TARGETS = "(select page_id, dense_rank() over (order by target) - 1 as k from (select distinct page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) as target from pages))"
_PAGES = r"(select page_id, regexp_extract(url, '(example\.(?:com|net|org))', 1) as domain, regexp_extract(url, '^https?://[^/]+/([a-z]+)/', 1) as lang from pages)"

#: Relation -> head type, tail type, head key, tail key, from.
EDGES = {
    "nation_hosts_customer": ("nation", "customer", "c_nationkey", "c_custkey", "customer"),
    "segment_covers_customer": ("segment", "customer", "k", "c_custkey", _dense("customer", "c_custkey", "c_mktsegment")),
    "customer_buys_from_supplier": ("customer", "supplier", "o_custkey", "l_suppkey", _ORDER_LINES),
    "supplier_sells_to_customer": ("supplier", "customer", "l_suppkey", "o_custkey", _ORDER_LINES),
    "customer_buys_part": ("customer", "part", "o_custkey", "l_partkey", _ORDER_LINES),
    "customer_placed_order": ("customer", "order", "o_custkey", "o_orderkey", "orders"),
    "order_contains_part": ("order", "part", "l_orderkey", "l_partkey", "lineitem"),
    "part_supplied_by": ("part", "supplier", "l_partkey", "l_suppkey", "lineitem"),
    "brand_has_part": ("brand", "part", r"cast(regexp_extract(p_brand, '(\d+)', 1) as bigint)", "p_partkey", "part"),
    "type_has_part": ("ptype", "part", "k", "p_partkey", _dense("part", "p_partkey", "p_type")),
    "supplier_in_nation": ("supplier", "nation", "s_suppkey", "s_nationkey", "supplier"),
    "nation_hosts_supplier": ("nation", "supplier", "s_nationkey", "s_suppkey", "supplier"),
    "nation_in_region": ("nation", "region", "n_nationkey", "n_regionkey", "nation"),
    "region_has_nation": ("region", "nation", "n_regionkey", "n_nationkey", "nation"),
    "user_did_type": ("user", "etype", "user_id", "k", _dense("events", "user_id", "event_type")),
    "type_attracts_user": ("etype", "user", "k", "user_id", _dense("events", "user_id", "event_type")),
    "bucket_attracts_user": ("bucket", "user", "cast(json_extract(props, '$.k') as bigint)", "user_id", "events"),
    "ptype_sold_by_supplier": ("ptype", "supplier", "k", "l_suppkey", _dense("part", "p_partkey", "p_type") + " join lineitem on p_partkey = l_partkey"),
    "lang_has_doc": ("lang", "doc", "k", "doc_id", _dense("documents", "doc_id", "lang")),
    "source_has_doc": ("source", "doc", "k", "doc_id", _dense("documents", "doc_id", "source")),
    "doc_mentions_token": ("doc", "token", "doc_id", "k", _TOKENS),
    "domain_has_page": ("domain", "page", "k", "page_id", _dense(_PAGES, "page_id", "domain")),
    "lang_has_page": ("lang", "page", "k", "page_id", _dense(_PAGES, "page_id", "lang")),
    "page_links_target": ("page", "target", "page_id", "k", _TARGETS),
    "role_speaks_in_conversation": ("role", "conv", "k", "conv_id", _dense("conversations", "conv_id", "role")),
}


def edge_sql(relation: str) -> str:
    h, t, hk, tk, source = EDGES[relation]
    return f"select distinct '{relation}' as r, '{h}' as h_type, cast({CODES[h] * SPAN} + {hk} as bigint) as h, '{t}' as t_type, cast({CODES[t] * SPAN} + {tk} as bigint) as t from {source}"


def triples_sql(relations: list[str]) -> str:
    return " union all ".join(edge_sql(r) for r in relations)


def graph_ctes(relations: list[str], dim: int = 8, binding: str = "composed", both: bool = False) -> list[str]:
    """triples, vec (eid, vec) and relv (r, vec); with both, every edge also turned round."""
    offsets = " ".join(f"when {CODES[t]} then {OFFSETS[t]}" for t in CODES)
    cells = f"range(1, {dim + 1})"
    if binding == "composed":
        vec = f"select p.eid, list_transform({cells}, lambda i: 4 * x.q[i] + y.q[i]) as vec from places p join q x on x.vec_id = p.a join q y on y.vec_id = p.b"
    else:
        vec = f"select e.eid, list_transform({cells}, lambda i: 4 * q.q[i]) as vec from ent e join q on q.vec_id = e.eid % {SPAN}"
    ctes = [
        f"base as ({triples_sql(relations)})",
        "ent as (select h as eid from base union select t from base)",
        "n as (select count(*) as n from embeddings)",
        f"q as (select vec_id, list_transform(embedding[1:{dim}], lambda x: cast(floor(cast(x as double) * 1048576) as bigint)) as q from embeddings)",
        f"offs as (select eid, eid % {SPAN} as k, case eid // {SPAN} {offsets} end as o from ent)",
        "places as (select eid, (k + o) % n as a, ((k // n) * 17 + k + o + 1) % n as b from offs, n)",
        f"vec as ({vec})",
        f"diffs as (select r, i, cast(sum(vt.vec[i] - vh.vec[i]) as bigint) as s, count(*) as c from base join vec vh on vh.eid = h join vec vt on vt.eid = t, (select unnest({cells}) as i) group by r, i)",
        "relv0 as (select r, list((s - ((s % c) + c) % c) // c order by i) as vec from diffs group by r)",
    ]
    if both:
        ctes += [
            "triples as (select * from base union all select 'inv:' || r, t_type, t, h_type, h from base)",
            "relv as (select * from relv0 union all select 'inv:' || r, list_transform(vec, lambda x: -x) from relv0)",
        ]
    else:
        ctes += ["triples as (select * from base)", "relv as (select * from relv0)"]
    return ctes


def _score(a: str, b: str, dim: int) -> str:
    return f"(cast(1 as double) - cast(list_sum(list_transform(range(1, {dim + 1}), lambda i: abs({a}[i] - {b}[i]))) as double) / {UNIT})"


def _composite(name: str, anchor: int, relation: str, dim: int) -> str:
    return f"{name} as (select list_transform(range(1, {dim + 1}), lambda i: v.vec[i] + w.vec[i]) as comp from vec v, relv w where v.eid = {anchor} and w.r = '{relation}')"


def _eid(anchor: tuple[str, int]) -> int:
    return CODES[anchor[0]] * SPAN + anchor[1]


def hop1_ctes(q: ThreeHopQuery, dim: int = 8) -> list[str]:
    keep = {"role": "", "linked": " and {e} in (select t from triples where r = '{r}' and h = {a})", "unlinked": " and {e} not in (select t from triples where r = '{r}' and h = {a})"}[q.candidates1]
    keep = keep.format(e="o.eid", r=q.relation1, a=_eid(q.anchor1))
    join = "join vec v on v.eid = o.eid" if q.missing == "drop" else "left join vec v on v.eid = o.eid"
    score = _score("c.comp", "v.vec", dim)
    if q.missing != "drop":
        score = f"case when v.vec is null then cast('-inf' as double) else {score} end"
    return [
        f"role1 as (select distinct {q.role1_end} as eid from triples where r = '{q.role1 or q.relation1}')",
        _composite("c1", _eid(q.anchor1), q.relation1, dim),
        f"s1 as (select o.eid, {score} as score from role1 o {join}, c1 c where true{keep})",
        f"hop1 as (select eid, score, row_number() over (order by score desc, eid) as rank from s1 qualify row_number() over (order by score desc, eid) <= {q.k})",
    ]


def hop2_ctes(q: ThreeHopQuery, dim: int = 8) -> list[str]:
    score = {"replace": "s", "sum": "f + s", "min": "least(f, s)", "keep_first": "s"}[q.combine]
    shown = "f" if q.combine == "keep_first" else "o"
    inner = _score("c.comp", "v.vec", dim)
    return [
        _composite("c2", _eid(q.anchor2), q.relation2, dim),
        f"s2 as (select eid, f, {score} as o from (select h.eid, h.score as f, case when v.vec is null then cast('-inf' as double) else {inner} end as s from hop1 h left join vec v on v.eid = h.eid, c2 c))",
        f"hop2 as (select eid, {shown} as score, row_number() over (order by o desc, eid) as rank from s2 qualify row_number() over (order by o desc, eid) <= {q.k2 or q.k})",
    ]


def hop3_ctes(q: ThreeHopQuery, dim: int = 8) -> list[str]:
    keep = {
        "role": "",
        "linked": f" and exists (select 1 from triples x where x.r = '{q.relation3}' and x.h = c.head and x.t = o.eid)",
        "unlinked": f" and not exists (select 1 from triples x where x.r = '{q.relation3}' and x.h = c.head and x.t = o.eid)",
    }[q.candidates3]
    join, score = "join", _score("c.comp", "v.vec", dim)
    if q.missing != "drop":
        join, score = "left join", f"case when v.vec is null then cast('-inf' as double) else {score} end"
    out = [
        f"role3 as (select distinct {q.role3_end} as eid from triples where r = '{q.role3 or q.relation3}')",
        f"c3 as (select h.eid as head, list_transform(range(1, {dim + 1}), lambda i: v.vec[i] + w.vec[i]) as comp from hop2 h join vec v on v.eid = h.eid, relv w where w.r = '{q.relation3}')",
        f"s3 as (select c.head, o.eid, {score} as score from role3 o {join} vec v on v.eid = o.eid, c3 c where true{keep})",
        f"per_head as (select head, eid, score, row_number() over (partition by head order by score desc, eid) as rank from s3 qualify row_number() over (partition by head order by score desc, eid) <= {q.k})",
    ]
    if q.output == "merged_pairs":
        out.append(f"hop3 as (select head, eid, score, row_number() over (order by score desc, eid, head) as rank from per_head qualify row_number() over (order by score desc, eid, head) <= {q.k})")
    elif q.output == "merged_entities":
        out.append("best as (select eid, max(score) as score from per_head group by eid)")
        out.append(f"hop3 as (select eid, score, row_number() over (order by score desc, eid) as rank from best qualify row_number() over (order by score desc, eid) <= {q.k})")
    else:
        out.append("hop3 as (select * from per_head)")
    return out


def statement(ctes: list[str], select: str) -> str:
    return "with " + ",\n".join(ctes) + "\n" + select


def question_sql(q: ThreeHopQuery, upto: int = 3, dim: int = 8, binding: str = "composed") -> str:
    ctes = graph_ctes(q.relations(), dim, binding) + hop1_ctes(q, dim)
    if upto > 1:
        ctes += hop2_ctes(q, dim)
    if upto > 2:
        ctes += hop3_ctes(q, dim)
    return statement(ctes, f"select * from hop{upto}")


def path_ctes(source: int, target: int | str, hops: int, k: int, prune: str, dim: int = 8, scorer: str = "translate_sum") -> list[str]:
    """Levels as CTEs; found (path, rels, score, hops, rank). A target is an id, or a select of the ids of a role."""
    start = f"f0 as (select [v.eid] as path, cast([] as varchar[]) as rels, v.vec as pvec, v.vec as lvec, v.eid as last, cast(0 as double) as score from vec v where v.eid = {source})"
    out, hits = [start], []
    cells = f"range(1, {dim + 1})"
    if scorer == "untyped":
        edges, rel, base = "(select distinct h, '' as r, t from triples)", "", "f.pvec"
        pvec = f"list_transform({cells}, lambda i: (f.pvec[i] * len(f.path) + v.vec[i] - (((f.pvec[i] * len(f.path) + v.vec[i]) % (len(f.path) + 1)) + len(f.path) + 1) % (len(f.path) + 1)) // (len(f.path) + 1))"
        total = "one"
    else:
        edges, rel, base, pvec = "triples", " join relv w on w.r = e.r", f"list_transform({cells}, lambda i: f.{'pvec' if scorer == 'translate_end' else 'lvec'}[i] + w.vec[i])", "base" if scorer == "translate_end" else "f.pvec"
        total = {"translate_sum": "before + one", "translate_end": "one", "bottleneck": "case when len(up) = 0 then one else least(before, one) end"}[scorer]
    for level in range(1, hops + 1):
        last = f" and e.t in ({target})" if level == hops else ""
        out.append(
            f"g{level} as (select path, rels, pvec, lvec, last, up, {total} as score, parent from (select list_append(f.path, e.t) as path, list_append(f.rels, e.r) as rels, {base} as base, {pvec if pvec != 'base' else base} as pvec, v.vec as lvec, e.t as last, f.rels as up, f.path as parent, f.score as before, "
            f"{_score(base, 'v.vec', dim)} as one from f{level - 1} f join {edges} e on e.h = f.last{rel} join vec v on v.eid = e.t where not list_contains(f.path, e.t){last}))"
        )
        hits.append(f"select path, rels, score, cast({level} as bigint) as hops from g{level} where last in ({target})")
        if level < hops:
            cut = ""
            if prune == "per_path":
                cut = f" qualify row_number() over (partition by parent, up order by score desc, path, rels) <= {k}"
            elif prune == "global":
                cut = f" qualify row_number() over (order by score desc, path, rels) <= {k}"
            out.append(f"f{level} as (select path, rels, pvec, lvec, last, score from g{level} where last not in ({target}){cut})")
    out.append(f"hits as ({' union all '.join(hits)})")
    limit = "" if prune == "none" else f" qualify row_number() over (order by score desc, path, rels) <= {k}"
    out.append(f"found as (select path, rels, score, hops, row_number() over (order by score desc, path, rels) as rank from hits{limit})")
    return out


PATH_COLUMNS = "select array_to_string(path, '>') as path, array_to_string(rels, '>') as rels, score, hops, rank from found"


def path_sql(relations: list[str], source: int, target: int | str, hops: int, k: int, prune: str, both: bool, scorer: str = "translate_sum") -> str:
    return statement(graph_ctes(relations, both=both) + path_ctes(source, target, hops, k, prune, scorer=scorer), PATH_COLUMNS)
