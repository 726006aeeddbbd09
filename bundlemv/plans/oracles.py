"""DuckDB SQL that answers the same questions without blocks, bundles or bins where a method is under test."""

from __future__ import annotations

LINES = "l_linenumber, l_partkey, l_suppkey, l_extendedprice"


def _count(table: str) -> str:
    return f"(select count(*) from {table})"


def pairs(group: str, member: str) -> str:
    return f"select distinct a.{member} as src, b.{member} as dst from lineitem a join lineitem b on a.{group} = b.{group} where a.{member} <> b.{member}"


_PATHS = "select distinct page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) as path from pages"
_PAGE_LINKS = f"with pp as ({_PATHS}) select distinct a.page_id as src, b.page_id as dst from pp a join pp b on a.path = b.path where a.page_id <> b.page_id"
_HOSTS = "select page_id, dense_rank() over (order by regexp_extract(url, '://([^/:?#]+)', 1)) - 1 as h from pages"


def kronecker(scale: int, edge_factor: int = 16, seeds: str | None = None) -> str:
    """seeds: a relation t(i), if not a range."""
    steps = [f"k0 as materialized (select (i * 2654435761 + 12345) % 2147483647 as st, 0::bigint as src, 0::bigint as dst from {seeds or f'range({edge_factor << scale}) t(i)'})"]
    for i in range(scale):
        steps.append(
            f"k{i + 1} as materialized (select st * 48271 % 2147483647 as st, src * 2 + (case when st % 10000 >= 7600 then 1 else 0 end) as src, "
            f"dst * 2 + (case when (st % 10000 >= 5700 and st % 10000 < 7600) or st % 10000 >= 9500 then 1 else 0 end) as dst from k{i})"
        )
    return f"with {', '.join(steps)} select distinct src, dst from k{scale}"


#: name -> (SQL of src, dst[, weight]; SQL of the number of vertices)
GRAPHS: dict[str, tuple[str, str]] = {
    "copurchase": (pairs("l_orderkey", "l_partkey"), _count("part")),
    "supplier_mesh": (pairs("l_orderkey", "l_suppkey"), _count("supplier")),
    "lineseq": (f"select distinct src, dst from (select l_partkey as src, lead(l_partkey) over (partition by l_orderkey order by {LINES}) as dst from lineitem) where dst is not null and src <> dst", _count("part")),
    "cust_part": (f"select distinct o_custkey as src, l_partkey + {_count('customer')} as dst from orders join lineitem on o_orderkey = l_orderkey", f"({_count('customer')} + {_count('part')})"),
    "user_flow": ("select distinct src, dst from (select user_id as src, lead(user_id) over (order by ts, event_id) as dst from events) where dst is not null and src <> dst", "(select max(user_id) + 1 from events)"),
    "page_links": (_PAGE_LINKS, _count("pages")),
    "page_anchor": (f"with pp as ({_PATHS}) select page_id as src, dense_rank() over (order by path) - 1 + {_count('pages')} as dst from pp", f"({_count('pages')} + (select count(distinct path) from ({_PATHS})))"),
    "host_links": (f"with h as ({_HOSTS}) select a.h as src, b.h as dst, count(*)::double as weight from ({_PAGE_LINKS}) e join h a on a.page_id = e.src join h b on b.page_id = e.dst group by all", f"(select max(h) + 1 from ({_HOSTS}))"),
    "nation_trade": ("select c_nationkey::bigint as src, s_nationkey::bigint as dst, round(sum(l_extendedprice * (1 - l_discount)), 4) as weight from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join supplier on l_suppkey = s_suppkey group by all", _count("nation")),
    "knn8": ("""with v as materialized (select vec_id, cast(embedding as double[]) as e from embeddings), u as materialized (select vec_id, list_transform(e, lambda x: x / sqrt(list_dot_product(e, e))) as e from v),
        s as (select a.vec_id as src, b.vec_id as dst, round(list_dot_product(a.e, b.e), 6) as weight from u a join u b on a.vec_id <> b.vec_id)
        select src, dst, weight from (select *, row_number() over (partition by src order by weight desc, dst) as r from s) where r <= 8""", _count("embeddings")),
    "kronecker": (kronecker(10), "1024"),
    "banded": ("select i as src, i + j as dst from range(4095) t(i), range(1, 9) s(j) where i + j < 4096", "4096"),
    "worked9": ("select * from (values (2,6),(2,7),(4,3),(4,5),(6,3),(6,4),(7,0),(7,2),(8,1),(8,7)) t(src, dst)", "9"),
}


#: Of the graphs that are made up, forms over the given tables.
FROM_TABLES: dict[str, str] = {
    "kronecker": kronecker(10, seeds="(select o_orderkey as i from orders)"),
    "banded": "select p_partkey as src, p_partkey + j as dst from part, range(1, 9) s(j) where p_partkey + j in (select p_partkey from part)",
    "worked9": f"select distinct src % 9 as src, dst % 9 as dst from ({GRAPHS['lineseq'][0]}) where src % 9 <> dst % 9",
}


def graph(name: str) -> str:
    return GRAPHS[name][0]


def n_of(name: str) -> str:
    return GRAPHS[name][1]


def order_line(label: str) -> str:
    first = {"order": "l_orderkey", "shipdate": "l_shipdate, l_orderkey", "part": "l_partkey, l_orderkey"}[label]
    return f"select l_orderkey as i, row_number() over (order by {first}, {LINES}) - 1 as j from lineitem"


def edges(name: str) -> str:
    """CTE head with the edges as e and the vertex count as nn."""
    return f"with e as materialized (select * from ({graph(name)})), nn as materialized (select {n_of(name)}::bigint as n)"


def rank(name: str, iters: int = 10, damping: float = 0.85, dangling: str = "drop", weighted: bool = False, teleport: str | None = None, final: str = "select id, round(rank, 10) as rank from last") -> str:
    """Unrolled iterations of the definition: teleport plus damped shares of in-neighbours."""
    w = "weight" if weighted else "1"
    head = [edges(name) + ", v as materialized (select i::bigint as id from nn, range(nn.n) t(i))"]
    if dangling == "self":
        head.append(f"e2 as materialized (select src, dst, {w}::double as weight from e union all select id, id, 1.0 from v where id not in (select src from e))")
    else:
        head.append(f"e2 as materialized (select src, dst, {w}::double as weight from e)")
    head.append("o as materialized (select src as id, sum(weight) as w from e2 group by src)")
    head.append(f"t as materialized ({teleport or 'select id, 1.0::double / n as tele from v, nn'})")
    head.append("r0 as materialized (select id, 1.0::double / n as rank from v, nn)")
    for i in range(1, iters + 1):
        spread = f" + coalesce((select sum(rank) from r{i - 1} where id not in (select id from o)), 0) / (select n from nn)" if dangling == "spread" else ""
        head.append(
            f"s{i} as materialized (select e2.dst as id, sum(r.rank / o.w * e2.weight) as s from e2 join r{i - 1} r on r.id = e2.src join o on o.id = e2.src group by e2.dst), "
            f"r{i} as materialized (select v.id, {1 - damping!r} * coalesce(t.tele, 0) + {damping!r} * (coalesce(s.s, 0){spread}) as rank from v left join s{i} s on s.id = v.id left join t on t.id = v.id)"
        )
    return ", ".join(head) + f", last as (select * from r{iters}) " + final
