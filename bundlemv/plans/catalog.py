"""Every method, variant, baseline, measure and workload as a query, with its SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from bundlemv import graph as ga
from bundlemv.functions import blocks as udf
from bundlemv.graph import Graph, Matrix
from bundlemv.operators import blocks, cost, dense, labels, layout, rank, results, spmv, steps
from bundlemv.plans import oracles as sql
from bundlemv.session import drop_at_exit, scratch_path
from bundlemv.sources import files
from bundlemv.sources import workloads as wl
from bundlemv.sources.tables import load_table
from bundlemv.streaming import edges as stream

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}

Q = 64
ITERS = 10

GRAPHS: dict[str, Callable[[SparkSession, str], Graph]] = {
    "copurchase": wl.copurchase, "lineseq": wl.line_sequence, "cust_part": wl.customer_part, "supplier_mesh": wl.supplier_mesh,
    "user_flow": wl.user_flow, "page_links": wl.page_links, "page_anchor": wl.page_anchor, "host_links": wl.host_links,
    "nation_trade": wl.nation_trade, "knn8": wl.knn, "kronecker": lambda s, d: wl.kronecker(s, 10), "banded": lambda s, d: wl.banded(s, 4096, 8),
    "worked9": lambda s, d: wl.worked9(s),
}
#: Of the graphs that are made up, forms over the given tables.
FROM_TABLES: dict[str, Callable[[SparkSession, str], Graph]] = {
    "banded": wl.banded_parts, "kronecker": wl.kronecker_orders, "worked9": wl.nine_groups,
}


def add(name: str, query: Query, text: str | None = None) -> None:
    QUERIES[name] = query
    if text is not None:
        SQL[name] = text


def longs(df: DataFrame, *cols: str) -> DataFrame:
    return df.withColumns({c: F.col(c).cast("long") for c in cols})


def rounded(df: DataFrame, *cols: str, to: int = 10) -> DataFrame:
    return df.withColumns({c: F.round(c, to) for c in cols})


def joined(c: str) -> Column:
    return F.array_join(F.transform(c, lambda x: x.cast("string")), ",")


def on(name: str | Callable[[SparkSession, str], Graph], f: Callable[[Graph], DataFrame]) -> Query:
    return lambda s, d: f((GRAPHS[name] if isinstance(name, str) else name)(s, d))


# --- graphs ---------------------------------------------------------------------

for _name, (_text, _) in sql.GRAPHS.items():
    _text, _graph = sql.FROM_TABLES.get(_name, _text), FROM_TABLES.get(_name, _name)
    _weighted = _name in ("host_links", "nation_trade", "knn8")
    add(f"g_{_name}", on(_graph, lambda g: g.edges), f"select src::bigint as src, dst::bigint as dst{', weight' if _weighted else ''} from ({_text})")
for _label in ("order", "shipdate", "part"):
    add(f"g_order_line_by_{_label}", lambda s, d, x=_label: wl.order_line(s, d, x).entries.select("i", "j"), sql.order_line(_label))
add("m_part_supplier", lambda s, d: wl.part_supplier(s, d).entries, "select l_partkey as i, l_suppkey as j, sum(l_quantity) as w from lineitem group by all")

# --- structure --------------------------------------------------------------------

_E = sql.edges("copurchase")
_EC = sql.edges("cust_part")
_V = "select i::bigint as id from nn, range(nn.n) t(i)"
_DEG = "select v.id, coalesce(o.c, 0)::bigint as out_deg, coalesce(p.c, 0)::bigint as in_deg from ({v}) v left join (select src as id, count(*) as c from e group by 1) o using (id) left join (select dst as id, count(*) as c from e group by 1) p using (id)".format(v=_V)
add("degrees", on("cust_part", ga.degrees), f"{_EC} {_DEG}")
add("degree_histogram", on("copurchase", ga.degree_histogram), f"{_E}, d as ({_DEG}) select out_deg, count(*) as vertices from d group by 1")
add("degree_percentiles", on("copurchase", lambda g: ga.degree_percentiles(g, (0.5, 0.9, 0.99))), f"{_E}, d as ({_DEG}) select p, quantile_cont(out_deg, p) as out_deg from d, (values (0.5::double), (0.9), (0.99)) t(p) group by p".replace("quantile_cont(out_deg, p)", "case p when 0.5 then quantile_cont(out_deg, 0.5) when 0.9 then quantile_cont(out_deg, 0.9) else quantile_cont(out_deg, 0.99) end"))
add("graph_summary", on("cust_part", ga.summary), f"""{_EC}, d as ({_DEG}) select count(*) as n, sum(out_deg)::bigint as m, count(*) filter (out_deg = 0) as sinks, count(*) filter (in_deg = 0) as sources,
    count(*) filter (out_deg = 0 and in_deg = 0) as isolated, max(out_deg) as max_out, max(in_deg) as max_in, round(sum(out_deg) / count(*), 6) as mean_degree from d""")
add("sinks", on("cust_part", ga.sinks), f"{_EC} select id from ({_V}) where id not in (select src from e)")
add("sources", on("cust_part", ga.sources), f"{_EC} select id from ({_V}) where id not in (select dst from e)")
add("semi_targets", on("cust_part", ga.targets), f"{_EC} select distinct dst as id from e")
add("reciprocal_edges", on("lineseq", ga.reciprocal), f"{sql.edges('lineseq')} select a.src, a.dst from e a join e b on a.src = b.dst and a.dst = b.src")
add("reverse_graph", on("lineseq", lambda g: ga.reverse(g).edges), f"{sql.edges('lineseq')} select dst as src, src as dst from e")
add("symmetrized", on("lineseq", lambda g: ga.symmetrize(g).edges), f"{sql.edges('lineseq')} select src, dst from e union select dst, src from e")
add("subgraph", on("copurchase", lambda g: ga.subgraph(g, g.vertices.where("id % 5 = 0")).edges), f"{_E} select src, dst from e where src % 5 = 0 and dst % 5 = 0")
add("contracted", on("copurchase", lambda g: ga.contract(g, g.vertices.select(F.col("id").alias("old"), (F.col("id") % 10).alias("new")), 10).edges), f"{_E} select src % 10 as src, dst % 10 as dst, count(*)::double as weight from e group by all")
add("edges_loops_dropped", lambda s, d: ga.drop_loops(wl.user_flow_loops(s, d)).edges, f"{sql.edges('user_flow')} select src, dst from e")
add("edges_threshold", on("knn8", lambda g: ga.threshold(g, 0.5).edges), f"{sql.edges('knn8')} select src, dst, weight from e where weight >= 0.5")
add("edges_union", lambda s, d: ga.union(wl.copurchase(s, d), wl.line_sequence(s, d)), f"select src, dst from ({sql.graph('copurchase')}) union select src, dst from ({sql.graph('lineseq')})")
add("edges_except", lambda s, d: ga.minus(wl.copurchase(s, d), wl.line_sequence(s, d)), f"select src, dst from ({sql.graph('copurchase')}) except select src, dst from ({sql.graph('lineseq')})")
add("edges_sample_hash", on("copurchase", lambda g: ga.sample_edges(g, 1, 16)), f"{_E} select src, dst from e where ((src * 40503 + dst * 9973 + 17) % 65521) % 16 < 1")
add("dense_ids", lambda s, d: ga.dense_ids(load_table(s, d, "customer").select("c_name"), ["c_name"], "id"), "select c_name, row_number() over (order by c_name) - 1 as id from customer")
_ADJ = "string_agg(dst::varchar, ',' order by dst)"
add("adjacency_lists", on("lineseq", lambda g: g.edges.groupBy("src").agg(F.sort_array(F.collect_list("dst")).alias("d")).select("src", joined("d").alias("dsts"))), f"{sql.edges('lineseq')} select src, {_ADJ} as dsts from e group by src")

# --- blocks and layout ----------------------------------------------------------



def _parts(s: SparkSession, d: str) -> DataFrame:
    return load_table(s, d, "part").select(F.col("p_partkey").alias("id"))


_B = f"{_E}, b as (select src, dst, src // {Q} as src_block, dst // {Q} as dst_block from e)"
_P = f"{_B}, p as (select src_block, dst_block, count(distinct src) as n_values, count(*) as n_ids, string_agg(distinct src::varchar, ',') as x from b group by all)"
_LB = f"{sql.edges('lineseq')}, b as (select src, dst, src // {Q} as src_block, dst // {Q} as dst_block from e)"
add("assign_blocks", lambda s, d: longs(blocks.assign_blocks(blocks.assign_blocks(_parts(s, d), "id", Q, "shifted"), "id", 100, "divided"), "shifted", "divided"), f"select p_partkey as id, p_partkey // {Q} as shifted, p_partkey // 100 as divided from part")
add("block_table", on("cust_part", lambda g: longs(blocks.block_table(g, Q), "block")), f"{_EC}, d as ({_DEG}) select id // {Q} as block, min(id) as first, max(id) as last, count(*) as vertices, sum(out_deg)::bigint as out_edges, sum(in_deg)::bigint as in_edges from d group by 1")
add("block_matrix", on("copurchase", lambda g: longs(blocks.block_matrix(g, Q), "src_block", "dst_block")), f"{_P} select src_block, dst_block, n_ids as edges, n_values as bundles from p")
add("block_matrix_cube", on("copurchase", lambda g: longs(blocks.block_matrix_cube(g, 256), "src_block", "dst_block")), f"{_E} select coalesce(src // 256, -1) as src_block, coalesce(dst // 256, -1) as dst_block, count(*) as edges from e group by cube (src // 256, dst // 256)")
add("block_matrix_rollup", on("copurchase", lambda g: longs(blocks.block_matrix_rollup(g, 256), "src_block", "dst_block")), f"{_E} select coalesce(src // 256, -1) as src_block, coalesce(dst // 256, -1) as dst_block, count(*) as edges from e group by rollup (src // 256, dst // 256)")
add("block_totals", on("copurchase", lambda g: longs(blocks.block_totals(g, 256), "src_block", "dst_block")), f"{_E} select src // 256 as src_block, -1 as dst_block, count(*) as edges from e group by 1 union all select -1, dst // 256, count(*) from e group by 2")
add("block_pivot", on("nation_trade", lambda g: longs(blocks.block_pivot(g, 9, 3), "src_block")), f"{sql.edges('nation_trade')} select (src // 9)::bigint as src_block, count(*) filter (dst // 9 = 0) as to_0, count(*) filter (dst // 9 = 1) as to_1, count(*) filter (dst // 9 = 2) as to_2 from e group by 1")
add("bundles", on("lineseq", lambda g: longs(layout.bundles(g, Q).select("src", "dst_block", joined("dsts").alias("dsts"), F.size("dsts").alias("size")), "dst_block", "size")), f"{_LB} select src, dst_block, {_ADJ} as dsts, count(*) as size from b group by src, dst_block")
add("first_edges", on("copurchase", lambda g: longs(layout.first_edges(g, Q), "src_block", "dst_block")), f"{_B} select src, min(dst) as dst, src_block, dst_block from b group by src, src_block, dst_block")
_CODE = "case when dst = min(dst) over (partition by src, dst_block) then dst + (-9223372036854775808) else dst end"
add("dest_lists_flagged", on("copurchase", lambda g: longs(layout.dest_lists(g, Q), "src_block", "dst_block")), f"{_B} select dst_block, src_block, src, dst, dst = min(dst) over (partition by src, dst_block) as flag, {_CODE} as code from b")


def _roundtrip(g: Graph) -> DataFrame:
    ident, first = layout.decode_flag(F.col("code"))
    return layout.dest_lists(g, Q).select("src", "dst", ident.alias("decoded"), first.alias("flag"))


add("flag_roundtrip", on("copurchase", _roundtrip), f"{_B} select src, dst, dst as decoded, dst = min(dst) over (partition by src, dst_block) as flag from b")
for _kind, _col in (("values", "n_values"), ("ids", "n_ids")):
    _n = _kind[:-1]
    add(f"{_n}_offsets", on("copurchase", lambda g, k=_kind: longs(layout.write_offsets(g, Q, k), "src_block", "dst_block")), f"{_P} select src_block, dst_block, {_col} as n, coalesce(sum({_col}) over (partition by dst_block order by src_block rows between unbounded preceding and 1 preceding), 0)::bigint as off from p")
add("offsets_disjoint", on("copurchase", lambda g: longs(layout.offsets_disjoint(layout.write_offsets(g, Q)), "dst_block")), f"{_P} select dst_block, sum(n_values)::bigint as size, true as disjoint from p group by 1")
add("layout_edges", on("copurchase", lambda g: longs(layout.block_layout(g, Q), "src_block", "dst_block")), f"{_B} select distinct src_block, dst_block, src from b")
_SRCS = "string_agg(src::varchar, ',' order by src)"
add("layout_transposed", on("lineseq", lambda g: longs(layout.transpose_layout(layout.block_layout(g, Q)).select("src_block", "dst_block", joined("srcs").alias("srcs")), "src_block", "dst_block")), f"{_LB} select src_block, dst_block, {_SRCS} as srcs from (select distinct src_block, dst_block, src from b) group by 1, 2")
add("layout_csr", on("copurchase", lambda g: longs(layout.layout_csr(g, Q), "src_block", "dst_block")), f"""{_P}, k as (select (n + {Q - 1}) // {Q} as k from nn), c as (select i as src_block, j as dst_block from k, range(k.k) t(i), range(k.k + 1) u(j))
    select c.src_block, c.dst_block, coalesce(sum(coalesce(n_values, 0)) over (partition by c.src_block order by c.dst_block rows between unbounded preceding and 1 preceding), 0)::bigint as off from c left join p using (src_block, dst_block)""")
add("layout_onepass", on("lineseq", lambda g: longs(layout.build_onepass(g, Q).withColumn("srcs", joined("srcs")), "src_block", "dst_block")), f"""{_LB}, p as (select src_block, dst_block, count(distinct src) as n_values, count(*) as n_ids from b group by all), l as (select src_block, dst_block, {_SRCS} as srcs from (select distinct src_block, dst_block, src from b) group by 1, 2)
    select src_block, dst_block, srcs, n_values, n_ids, coalesce(sum(n_values) over w, 0)::bigint as value_off, coalesce(sum(n_ids) over w, 0)::bigint as id_off from p join l using (src_block, dst_block) window w as (partition by dst_block order by src_block rows between unbounded preceding and 1 preceding)""")
add("local_ids", on("copurchase", lambda g: longs(layout.local_ids(g, Q), "dst_block", "local")), f"{_B} select dst_block, src, dst, dst - dst_block * {Q} as local from b")
add("custom_blocks", lambda s, d: longs(blocks.custom_blocks(_parts(s, d), F.col("id") % 7), "new"), "select p_partkey as old, row_number() over (order by p_partkey % 7, p_partkey) - 1 as new from part")
_BAL = f"{_EC}, d as ({_DEG}), a as (select id, out_deg, coalesce(sum(out_deg) over (order by id rows between unbounded preceding and 1 preceding), 0) as ahead, sum(out_deg) over () as m from d), z as (select id, out_deg, least(7, ahead * 8 // m)::bigint as block from a)"
add("balanced_blocks", on("cust_part", lambda g: longs(blocks.balanced_blocks(g, 8), "block").groupBy("block").agg(F.count("*").alias("vertices"), F.sum("out_deg").alias("edges"))), f"{_BAL} select block, count(*) as vertices, sum(out_deg)::bigint as edges from z group by 1")


def _range_blocks(g: Graph) -> DataFrame:
    own = blocks.balanced_blocks(g, 8)
    return longs(blocks.by_bounds(g.vertices, blocks.bounds(own), 8), "block")


add("range_blocks", on("cust_part", _range_blocks), f"{_BAL} select id, block from z")

_PLANS = [(10**9, 128 << 20, 10), (100, 1 << 30, 8), (20_000, 32 << 20, 16), (3, 8, 1), (1, 1, 64), (5_000_000_000, 32 << 20, 4000)]
add("plan_width", lambda s, d: s.createDataFrame([(n, b, t, blocks.plan_width(n, b, t)) for n, b, t in _PLANS], "n long, task_bytes long, tasks long, width long"),
    "select n, task_bytes, tasks, (1::bigint << floor(log2(least(greatest(1, task_bytes // 8), greatest(1, n // tasks))))::int) as width from (values " + ", ".join(f"({n}::bigint, {b}::bigint, {t}::bigint)" for n, b, t in _PLANS) + ") t(n, task_bytes, tasks)")

# --- files ------------------------------------------------------------------------


def _through(write: Callable[[Graph, str], None], read: Callable[[SparkSession, str], DataFrame]) -> Query:
    """Written to the shared folder and read again."""

    def query(s: SparkSession, d: str) -> DataFrame:
        path = scratch_path(s, "files")
        write(wl.line_sequence(s, d), path)
        drop_at_exit(s, path)
        return read(s, path)

    return query


_LINES = f"{sql.edges('lineseq')} select src, dst from e"
for _fmt, _sep in (("csv", ","), ("tsv", "\t"), ("ssv", " ")):
    add(f"read_edges_{_fmt}", _through(lambda g, p, x=_sep: g.edges.write.option("sep", x).csv(p), lambda s, p, f=_fmt: files.read_edges(s, p, f)), _LINES)
for _fmt in ("json", "parquet", "orc"):
    add(f"read_edges_{_fmt}", _through(lambda g, p, f=_fmt: g.edges.write.format(f).save(p), lambda s, p, f=_fmt: files.read_edges(s, p, f)), _LINES)
add("read_adjacency", _through(files.write_adjacency, files.read_adjacency), _LINES)
add("write_ranks", _through(lambda g, p: files.write_ranks(rank.run(g, iters=2), p), lambda s, p: rounded(s.read.parquet(p), "rank")), sql.rank("lineseq", 2))

# --- one step and ranks -----------------------------------------------------------


def _ranked(name: str, method: str, iters: int = ITERS, top: bool = False, **options) -> Query:
    def query(s: SparkSession, d: str) -> DataFrame:
        g = GRAPHS[name](s, d).persist()
        if g.twins is not None:
            return rounded(rank.run_folded(g.twins, method, iters=iters, **options), "rank")
        out = rounded(rank.run(g, method, iters=iters, **options), "rank")
        g.release()
        return out

    return query


for _name, _method in {
    "pull": "pull", "per_edge": "per_edge", "per_edge_resend": "per_edge_resend", "edge_scan": "edge_scan", "naive": "naive", "bundled_adjacency": "bundled_adjacency",
    "bundled_layout": "bundled_rows", "bundled_branchless": "bundled_prefix", "bundled_packed": "bundled_nested", "bundled_positions": "bundled", "bundled_arrow": "bundled_arrow", "bundled_resend": "bundled_resend",
}.items():
    add(f"step_{_name}", _ranked("cust_part", _method, 1), sql.rank("cust_part", 1))
add("step_weighted", _ranked("nation_trade", "bundled", 1), sql.rank("nation_trade", 1, weighted=True))
for _name, _method in {
    "pull": "pull", "per_edge": "per_edge", "per_edge_resend": "per_edge_resend", "edge_scan": "edge_scan", "naive": "naive", "bundled": "bundled",
    "bundled_adjacency": "bundled_adjacency", "bundled_branch": "bundled_rows", "bundled_nested": "bundled_nested", "bundled_prefix": "bundled_prefix", "bundled_arrow": "bundled_arrow", "bundled_resend": "bundled_resend",
}.items():
    add(f"rank_{_name}", _ranked("copurchase", _method), sql.rank("copurchase"))
add("rank_hub_chunks", _ranked("copurchase", "bundled", chunk_edges=1000), sql.rank("copurchase"))


def _from_layout(s: SparkSession, d: str) -> DataFrame:
    """Written once, opened again, and run without the edges."""
    path = scratch_path(s, "layout")
    files.write_layout(wl.copurchase(s, d).persist(), path, 128)
    drop_at_exit(s, path)
    return rounded(rank.run(None, prepared=files.prepared_layout(s, path), iters=ITERS), "rank")


def _four_bytes(s: SparkSession, d: str) -> DataFrame:
    """Values of 4 bytes against values of 8: whether the ranks agree to about seven digits."""
    g = wl.copurchase(s, d).persist()
    a, b = (rank.run(g, iters=ITERS, value_type=t).withColumnRenamed("rank", t) for t in ("float", "double"))
    return a.join(b, "id").agg(F.count("*").alias("vertices"), (F.max(F.abs(F.col("float") / F.col("double") - 1)) < 1e-5).alias("close"))


for _name, _mode in (("kronecker", "drop"), ("worked9", "spread"), ("nation_trade", "drop"), ("worked9", "self")):
    add(f"rank_dense_{_name}_{_mode}", on(_name, lambda g, m=_mode: rounded(dense.dense_rank(g, ITERS, dangling=m), "rank")), sql.rank(_name, dangling=_mode, weighted=_name == "nation_trade"))
add("rank_from_layout", _from_layout, sql.rank("copurchase"))
add("rank_four_bytes", _four_bytes, f"{_E} select n as vertices, true as close from nn")
add("rank_pull_balanced", _ranked("copurchase", "pull", balanced=True), sql.rank("copurchase"))
add("rank_pull_shuffled", _ranked("copurchase", "pull", max_broadcast=0), sql.rank("copurchase"))
for _name in ("page_links", "user_flow", "kronecker", "lineseq", "supplier_mesh", "page_anchor"):
    add(f"rank_{_name}", _ranked(_name, "bundled"), sql.rank(_name))
for _mode in ("drop", "spread", "self"):
    add(f"rank_dangling_{_mode}", _ranked("cust_part", "bundled", dangling=_mode), sql.rank("cust_part", dangling=_mode))
for _method in ("bundled", "pull", "per_edge"):
    add(f"rank_weighted_{_method}", _ranked("nation_trade", _method), sql.rank("nation_trade", weighted=True))


def _personal(s: SparkSession, d: str) -> DataFrame:
    g = wl.copurchase(s, d).persist()
    return rounded(rank.run(g, iters=ITERS, personalization=g.vertices.where("id < 4").withColumn("tele", F.lit(0.25))), "rank")


add("rank_personalized", _personal, sql.rank("copurchase", teleport="select id, 0.25::double as tele from v where id < 4"))
add("rank_top20", lambda s, d: longs(rounded(results.top(rank.run(wl.copurchase(s, d).persist(), iters=ITERS), 20), "rank"), "pos"), sql.rank("copurchase", final="select id, round(rank, 10) as rank, row_number() over (order by rank desc, id) as pos from last qualify pos <= 20"))
add("rank_mass_by_iteration", lambda s, d: rounded(rank.masses(wl.customer_part(s, d).persist(), iters=5), "mass"), sql.rank("cust_part", 5, final=" union all ".join(f"select {i}::bigint as iteration, round(sum(rank), 10) as mass from r{i}" for i in range(6))))
add("rank_until_settled", lambda s, d: rounded(rank.run(wl.copurchase(s, d).persist(), iters=60, tol=1e-9), "rank", to=7), sql.rank("copurchase", 20, final="select id, round(rank, 7) as rank from last"))
add("topk_per_block", lambda s, d: longs(rounded(results.top_per_block(rank.run(wl.copurchase(s, d).persist(), iters=ITERS), 256, 3), "rank"), "block", "pos"), sql.rank("copurchase", final="select id, round(rank, 10) as rank, id // 256 as block, row_number() over (partition by id // 256 order by rank desc, id) as pos from last qualify pos <= 3"))


add("rank_places", lambda s, d: longs(rounded(results.rank_places(rounded(rank.run(wl.copurchase(s, d).persist(), iters=2), "rank"), 256), "percent", "cumulative"), "block", "pos", "dense_pos", "quarter"), sql.rank("copurchase", 2, final="""select id, id // 256 as block, rank() over w as pos, dense_rank() over w as dense_pos,
    ntile(4) over (partition by id // 256 order by round(rank, 10) desc, id) as quarter, round(percent_rank() over w, 10) as percent, round(cume_dist() over w, 10) as cumulative from last window w as (partition by id // 256 order by round(rank, 10) desc)"""))


def _outer_delta(s: SparkSession, d: str) -> DataFrame:
    g = wl.customer_part(s, d).persist()
    return rounded(results.delta(rank.run(g, iters=3), rank.run(g, "pull", iters=4)), "l1", "l2", "largest")


add("outer_delta", _outer_delta, sql.rank("cust_part", 4, final="select round(sum(abs(a.rank - b.rank)), 10) as l1, round(sqrt(sum((a.rank - b.rank) ** 2)), 10) as l2, round(max(abs(a.rank - b.rank)), 10) as largest from r3 a join r4 b using (id)"))
add("top_overlap", lambda s, d: results.top_overlap(rank.run(g := wl.copurchase(s, d).persist(), iters=2), rank.run(g, "naive", iters=6), 50), sql.rank("copurchase", 6, final=", a as (select id from r2 order by rank desc, id limit 50), b as (select id from r6 order by rank desc, id limit 50) select count(*) / 50 as overlap from a where id in (select id from b)"))


def _invariance(s: SparkSession, d: str) -> DataFrame:
    g = wl.copurchase(s, d).persist()
    perm = labels.random(g, 5)
    moved = rank.run(labels.relabel(g, perm).persist(), iters=3)
    return rounded(moved.join(perm, moved.id == perm.new).select(F.col("old").alias("id"), "rank"), "rank")


add("relabel_invariance", _invariance, sql.rank("copurchase", 3))


def _asof(s: SparkSession, d: str) -> DataFrame:
    events = load_table(s, d, "events").select("event_id", F.col("user_id").alias("id"), "ts")
    first = load_table(s, d, "events").where("event_id % 3 = 0").select(F.col("user_id").alias("id"), "ts", (F.col("event_id") / 1000).alias("rank"))
    return results.rank_asof(events, first.groupBy("id", "ts").agg(F.max("rank").alias("rank")))


add("asof_rank", _asof, "with s as (select user_id as id, ts, max(event_id / 1000) as rank from events where event_id % 3 = 0 group by all) select e.event_id, e.user_id as id, s.rank from events e asof left join s on e.user_id = s.id and e.ts >= s.ts")

# --- products ---------------------------------------------------------------------

_PS = "e as materialized (select l_partkey as i, l_suppkey as j, sum(l_quantity) as w from lineitem group by all)"


def _prices(s: SparkSession, d: str) -> DataFrame:
    return load_table(s, d, "part").select(F.col("p_partkey").alias("id"), F.col("p_retailprice").alias("x"))


for _method in ("bundled", "per_edge"):
    add(f"spmv_rectangular_{_method}", lambda s, d, m=_method: rounded(spmv.spmv(wl.part_supplier(s, d), _prices(s, d), 64, 16, method=m), "x", to=4), f"with {_PS} select j as id, round(sum(w * p_retailprice), 4) as x from e join part on p_partkey = i group by 1")
add("spmv_rectangular_transposed", lambda s, d: rounded(spmv.spmv(wl.part_supplier(s, d).transpose(), load_table(s, d, "supplier").select(F.col("s_suppkey").alias("id"), F.col("s_acctbal").alias("x")), 16, 64), "x", to=4), f"with {_PS} select i as id, round(sum(w * s_acctbal), 4) as x from e join supplier on s_suppkey = j group by 1")


def _square(g: Graph) -> Matrix:
    return Matrix(g.edges.select(F.col("src").alias("i"), F.col("dst").alias("j"), F.lit(1.0).alias("w")), g.n, g.n)


add("spmv_square", lambda s, d: rounded(spmv.spmv(_square(wl.copurchase(s, d)), _prices(s, d)), "x", to=4), f"{_E} select dst as id, round(sum(p_retailprice), 4) as x from e join part on p_partkey = src group by 1")


def _knn_product(s: SparkSession, d: str) -> DataFrame:
    g = wl.knn(s, d).persist()
    return rounded(spmv.spmv(Matrix(g.edges.select(F.col("src").alias("i"), F.col("dst").alias("j"), F.col("weight").alias("w")), g.n, g.n), g.vertices.select("id", (F.col("id") % 7).cast("double").alias("x"))), "x", to=6)


add("spmv_weighted_knn", _knn_product, f"{sql.edges('knn8')} select dst as id, round(sum(weight * (src % 7)), 6) as x from e group by 1")
add("spmv_power", lambda s, d: rounded(spmv.power(_square(wl.copurchase(s, d)), _prices(s, d), 3), "x"), f"{_E}, x0 as materialized (select p_partkey as id, p_retailprice as x from part)" + "".join(f", y{i} as materialized (select dst as id, sum(x) as x from e join x{i - 1} p on p.id = e.src group by 1), x{i} as materialized (select id, x / (select max(abs(x)) from y{i}) as x from y{i})" for i in (1, 2, 3)) + " select id, round(x, 10) as x from x3")
add("spmv_max_times", lambda s, d: rounded(spmv.spmv(wl.part_supplier(s, d), _prices(s, d), semiring="max_times"), "x", to=4), f"with {_PS} select j as id, round(max(w * p_retailprice), 4) as x from e join part on p_partkey = i group by 1")
add("spmv_or_and", lambda s, d: spmv.spmv(wl.part_supplier(s, d), _prices(s, d).select("id", F.when(F.col("id") % 97 == 0, 1.0).otherwise(0.0).alias("x")), semiring="or_and"), f"with {_PS} select j as id, max(case when i % 97 = 0 and w <> 0 then 1.0::double else 0 end) as x from e group by 1")
add("spmv_minplus_hops", on("lineseq", lambda g: spmv.hops(g.persist(), 0)), f"""with recursive e as materialized ({sql.graph('lineseq')}), h(id, x) as (select 0::bigint, 0 union select e.dst, h.x + 1 from h join e on e.src = h.id where h.x < 12) select id, min(x)::double as x from h group by 1""")
add("spmv_components", lambda s, d: spmv.component_labels(Graph(wl.knn(s, d).edges.select("src", "dst"), load_table(s, d, "embeddings").count()).persist()), f"""with recursive e as materialized (select src, dst from ({sql.graph('knn8')}) union select dst, src from ({sql.graph('knn8')})), v as (select vec_id as id from embeddings),
    c(id, root) as (select id, id from v union select e.dst, c.root from c join e on e.src = c.id) select id, min(root)::double as x from c group by 1""")

# --- labels -----------------------------------------------------------------------

_H = "(id * 1103515245 + 12345) % 2147483647"
add("label_original", on("copurchase", labels.original), f"{_E} select id as old, id as new from ({_V})")
add("label_random", on("copurchase", labels.random), f"{_E} select id as old, row_number() over (order by {_H}, id) - 1 as new from ({_V})")
add("label_degree", on("lineseq", labels.by_degree), f"{sql.edges('lineseq')}, d as ({_DEG}) select id as old, row_number() over (order by in_deg desc, id) - 1 as new from d")
add("label_by_column", lambda s, d: labels.by_column(load_table(s, d, "pages").select(F.col("page_id").alias("id"), "url"), "url"), "select page_id as old, row_number() over (order by url, page_id) - 1 as new from pages")
_SIG = "select v.id, s.sig from ({v}) v left join (select dst as id, min((src * 1103515245 + 12345) % 2147483647) as sig from e group by 1) s using (id)".format(v=_V)
add("label_parent_signature", on("page_links", labels.parent_signature), f"{sql.edges('page_links')}, g as ({_SIG}) select id as old, row_number() over (order by sig nulls last, id) - 1 as new from g")
add("label_hops", on("user_flow", lambda g: labels.by_hops(g.persist())), f"""with recursive e as materialized ({sql.graph('user_flow')}), nn as (select {sql.n_of('user_flow')}::bigint as n), h(id, x) as (select 0::bigint, 0 union select e.dst, h.x + 1 from h join e on e.src = h.id where h.x < 12),
    l as (select v.id, m.x from ({_V}) v left join (select id, min(x) as x from h group by 1) m using (id)) select id as old, row_number() over (order by x nulls last, id) - 1 as new from l""")
add("label_shared_parents", on("page_links", labels.shared_parents))

# --- costs ------------------------------------------------------------------------

_R = "count(*)::bigint as m, count(distinct (src, dst // {q}))::bigint as bundles, count(*) / count(distinct (src, dst // {q})) as r from e"
add("compression_ratio", on("copurchase", lambda g: rounded(cost.compression_ratio(g, Q), "r")), f"{_E} select {_R.format(q=Q)}".replace("count(*) / count(distinct (src, dst // 64)) as r", "round(count(*) / count(distinct (src, dst // 64)), 10) as r"))
add("compression_approx", on("copurchase", lambda g: cost.compression_ratio(g, Q, approx=True)))
for _name in ("copurchase", "cust_part", "kronecker", "banded"):
    add(f"compression_by_width_{_name}", on(_name, lambda g: rounded(cost.compression_by_width(g, list(range(4, 13))), "r")), f"{sql.edges(_name)} select s::bigint as shift, 1::bigint << s as q, ((n + (1::bigint << s) - 1) // (1::bigint << s))::bigint as k, count(*) as m, count(distinct (src, dst >> s)) as bundles, round(count(*) / count(distinct (src, dst >> s)), 10) as r from e, nn, range(4, 13) t(s) group by s, n")


def _by_label(g: Graph) -> DataFrame:
    g, out = g.persist(), None
    for name, perm in (("original", labels.original(g)), ("random", labels.random(g)), ("degree", labels.by_degree(g)), ("signature", labels.parent_signature(g))):
        own = cost.labelled_compression(g, perm, 16).select(F.lit(name).alias("label"), "m", "bundles", "r")
        out = own if out is None else out.union(own)
    return rounded(out, "r")


for _name in ("kronecker", "banded", "page_links"):
    _one = "select '{l}' as label, count(*) as m, count(distinct (a.new, b.new // 16)) as bundles, round(count(*) / count(distinct (a.new, b.new // 16)), 10) as r from e join {t} a on a.old = src join {t} b on b.old = dst"
    add(f"compression_by_label_{_name}", on(_name, _by_label), f"""{sql.edges(_name)}, d as ({_DEG}), g as ({_SIG}), p0 as (select id as old, id as new from d), p1 as (select id as old, row_number() over (order by {_H}, id) - 1 as new from d),
        p2 as (select id as old, row_number() over (order by in_deg desc, id) - 1 as new from d), p3 as (select id as old, row_number() over (order by sig nulls last, id) - 1 as new from g) """ + " union all ".join(_one.format(l=x, t=f"p{i}") for i, x in enumerate(("original", "random", "degree", "signature"))))


def _labelings(g: Graph, greedy: bool = False) -> dict[str, DataFrame]:
    own = {"original": labels.original(g), "random": labels.random(g)}
    return own | ({"greedy": labels.shared_parents(g)} if greedy else {"degree": labels.by_degree(g), "signature": labels.parent_signature(g)})


def _traffic_labels(name: str, greedy: bool = False) -> Query:
    def query(s: SparkSession, d: str) -> DataFrame:
        g = GRAPHS[name](s, d).persist()
        return rounded(rounded(cost.traffic_by_label(g, _labelings(g, greedy), 16), "r"), "bytes", to=2)

    return query


#: Bytes of the three methods, written out for the labelings' SQL: q = 16, ids and values of 8 bytes, lines of 64.
_BY_LABEL = (("pull", "m * (8 + miss * 64) + n * 16"), ("per_edge", "32 * m + n * 24"), ("bundled", "m * (8 + 8 / r + 16 / r) + k * k * 8 + 16 * n"))
for _name in ("kronecker", "banded", "page_links"):
    _one = "select '{l}' as label, count(*)::double as m, count(*) / count(distinct (a.new, b.new // 16)) as r, count(distinct (b.new // 16, a.new // 8)) / count(*) as miss from e join {t} a on a.old = src join {t} b on b.old = dst"
    _each = " union all ".join(f"select label, '{m}' as method, round(r, 10) as r, round({t}, 2) as bytes from x" for m, t in _BY_LABEL)
    add(f"traffic_by_label_{_name}", _traffic_labels(_name), f"""{sql.edges(_name)}, d as ({_DEG}), g as ({_SIG}), p0 as (select id as old, id as new from d), p1 as (select id as old, row_number() over (order by {_H}, id) - 1 as new from d),
        p2 as (select id as old, row_number() over (order by in_deg desc, id) - 1 as new from d), p3 as (select id as old, row_number() over (order by sig nulls last, id) - 1 as new from g),
        x as (select y.*, n::double as n, ((n + 15) // 16)::double as k from nn, (""" + " union all ".join(_one.format(l=x, t=f"p{i}") for i, x in enumerate(("original", "random", "degree", "signature"))) + f") y) {_each}")
for _name in ("kronecker", "page_links", "lineseq"):
    add(f"traffic_greedy_{_name}", _traffic_labels(_name, greedy=True))
for _name in ("copurchase", "kronecker"):
    add(f"traffic_by_width_{_name}", on(_name, lambda g: rounded(rounded(cost.traffic_by_width(g, list(range(4, 18))), "r"), "per_edge", "bundled", to=2)), f"""{sql.edges(_name)},
        x as (select s, 1::bigint << s as q, n::double as n, ((n + (1::bigint << s) - 1) // (1::bigint << s))::double as k, count(*)::double as m, count(*) / count(distinct (src, dst >> s)) as r from e, nn, range(4, 18) t(s) group by s, n)
        select s::bigint as shift, q, k::bigint as k, round(r, 10) as r, round(32 * m + n * 24, 2) as per_edge, round(m * (8 + 8 / r + 16 / r) + k * k * 8 + 16 * n, 2) as bundled, q * 8 as block_bytes, greatest(0, q * 8 - 262144) as overflow from x""")


def _lines_by_label(s: SparkSession, d: str) -> DataFrame:
    out = None
    for x in ("order", "shipdate", "part"):
        e = wl.order_line(s, d, x).entries
        own = cost.compression_ratio(Graph(e.select(F.col("i").alias("src"), F.col("j").alias("dst")), 0), 256).select(F.lit(x).alias("label"), "m", "bundles", "r")
        out = own if out is None else out.union(own)
    return rounded(out, "r")


add("compression_by_label_order_line", _lines_by_label, " union all ".join(f"select '{x}' as label, count(*) as m, count(distinct (i, j // 256)) as bundles, round(count(*) / count(distinct (i, j // 256)), 10) as r from ({sql.order_line(x)})" for x in ("order", "shipdate", "part")))
_CNT = f"{_E}, c as (select count(*) as m, count(distinct (src, dst // {Q})) as b from e)"
add("messages_by_method", on("copurchase", lambda g: cost.count_messages(g, Q)), f"{_CNT} " + " union all ".join(f"select '{n}' as method, {a} as messages, ({b})::bigint as bytes from c" for n, a, b in (
    ("per_edge", "m", "m * 8"), ("per_edge_resend", "m", "m * 16"), ("bundled", "b", "b * 8"), ("edge_scan", "m", "m * 16"), ("bundled_resend", "b", "b * 8 + m * 8"), ("pull", "0::bigint", "0"))))


def _sent(g: Graph) -> DataFrame:
    """Values in the streams that the methods really send."""
    g = g.persist()
    steps.allow_placement(g.spark)
    vertices = rank.vertex_table(g, Q).persist()
    shares = rank.first_ranks(g.n, vertices)
    rows = [(name, _sent_by(steps.METHODS[name](g, Q), shares)) for name in ("bundled", "bundled_nested", "bundled_rows", "bundled_adjacency", "bundled_arrow", "bundled_resend", "per_edge", "per_edge_resend")]
    vertices.unpersist()
    g.release()
    return g.spark.createDataFrame(rows, "method string, messages long")


def _sent_by(method: steps.Method, shares: DataFrame) -> int:
    """Counted at once, so that what one method keeps is gone before the next is made."""
    stream = method.scatter(shares)
    n = stream.agg(steps.count_values(stream)).first()[0]
    method.release()
    return n


add("messages_sent", on("copurchase", _sent), f"{_CNT} " + " union all ".join(f"select '{n}' as method, {a}::bigint as messages from c" for n, a in (
    ("bundled", "b"), ("bundled_nested", "b"), ("bundled_rows", "b"), ("bundled_adjacency", "b"), ("bundled_arrow", "b"), ("bundled_resend", "b"), ("per_edge", "m"), ("per_edge_resend", "m"))))
add("buffer_flushes", on("copurchase", lambda g: longs(steps.buffer_flushes(g, Q, 16), "dst_block")), f"{_P} select dst_block, sum(n_ids)::bigint as messages, sum((n_ids + 15) // 16)::bigint as flushes from p group by 1")
add("bin_switches", on("lineseq", lambda g: cost.count_bin_switches(g, Q)), f"""{sql.edges('lineseq')}, b as (select src, dst, src // {Q} as sb, dst // {Q} as db from e) select 'per_edge' as method, count(*) as switches from (select db, lag(db) over (partition by sb order by src, dst) as p from b) where p is null or p <> db
    union all select 'bundled', count(*) from (select distinct sb, db from b)""")
add("block_pairs", on("lineseq", lambda g: cost.nonempty_pairs(g, Q)), f"{sql.edges('lineseq')} select count(distinct (src // {Q}, dst // {Q})) as pairs, (((n + {Q - 1}) // {Q}) ** 2)::bigint as most from e, nn group by n")
add("miss_ratio_estimate", on("copurchase", lambda g: rounded(cost.est_miss_ratio(g, Q), "miss")), f"{_E} select count(distinct (dst // {Q}, src // 8)) as lines, round(count(distinct (dst // {Q}, src // 8)) / count(*), 10) as miss from e")
add("footprint", on("copurchase", lambda g: cost.memory_footprint(g, Q)), f"{_CNT}, k as (select n, (n + {Q - 1}) // {Q} as k from nn) select (b * 8)::bigint as value_bins, (m * 8)::bigint as id_bins, (b * 8)::bigint as layout, (k * k * 8)::bigint as offsets, (n * k * 8)::bigint as offsets_plain from c, k")
_MEAS = f"{_CNT}, x as (select n::double as n, m::double as m, ((n + {Q - 1}) // {Q})::double as k, m / b as r, (select count(distinct (dst // {Q}, src // 8)) from e) / m as miss, 64.0::double as line, 8.0::double as dv, 8.0::double as di from c, nn)"
_MODEL = {
    "pull": "m * (di + miss * line) + n * (di + dv)", "per_edge": "2 * m * (di + dv) + n * (di + 2 * dv)", "bundled": "m * (di * (1 + 1 / r) + 2 * dv / r) + k * k * di + 2 * n * dv",
}
_LIT = "x as (select 33500000.0::double as n, 1070000000.0::double as m, 512.0::double as k, 3.06::double as r, 1.0::double as miss, 64.0::double as line, 4.0::double as dv, 4.0::double as di)"
_ALL = " union all ".join(f"select '{m}' as method, round({t}, 2) as bytes from x" for m, t in _MODEL.items())
add("traffic_model_all", on("copurchase", lambda g: rounded(cost.models(cost.measured_params(g.persist(), Q)), "bytes", to=2)), f"{_MEAS} {_ALL}")
add("traffic_model_literal", lambda s, d: rounded(cost.models(cost.CURVE.frame(s)), "bytes", to=2), f"with {_LIT} {_ALL}")
_PARTSQL = {
    ("pull", "edge_reads"): "m * (di + miss * line)", ("pull", "vertex_reads_writes"): "n * (di + dv)", ("per_edge", "scatter_read"): "n * (di + dv) + m * di", ("per_edge", "scatter_write"): "m * dv",
    ("per_edge", "gather_read"): "m * (di + dv)", ("per_edge", "final_write"): "n * dv", ("bundled", "scatter_read"): "m / r * di + k * k * di + n * dv", ("bundled", "scatter_write"): "m / r * dv",
    ("bundled", "gather_read"): "m * di + m / r * dv", ("bundled", "final_write"): "n * dv",
}
add("traffic_parts", on("copurchase", lambda g: rounded(cost.parts(cost.measured_params(g.persist(), Q)), "bytes", to=2)), f"{_MEAS} " + " union all ".join(f"select '{m}' as method, '{p}' as part, round({t}, 2) as bytes from x" for (m, p), t in _PARTSQL.items()))
add("traffic_bounds", lambda s, d: rounded(cost.limits(cost.CURVE.frame(s)), "miss_best", "r_best"), f"with {_LIT} select m * di as pull_best, m * (di + line) as pull_worst, m * di as bundled_best, m * (2 * di + 2 * dv) as bundled_worst, round(n * dv / (m * line), 10) as miss_best, round(m / n, 10) as r_best from x")
_RS = [1.0, 2.0, 3.06, 5.0, 10.0, 20.0, 31.94]
add("traffic_curve_literal", lambda s, d: rounded(cost.curve(cost.CURVE.frame(s), _RS), "bytes", to=2), f"with {_LIT} select y.r, round(m * (di * (1 + 1 / y.r) + 2 * dv / y.r) + k * k * di + 2 * n * dv, 2) as bytes from (select n, m, k, dv, di from x), (select unnest({_RS}::double[]) as r) y")
#: The published sizes, values and ids of 4 bytes and lines of 64, on a measured graph.
_LITSIZE = f"{sql.edges('lineseq')}, x as (select count(*)::double as m, ((n + {Q - 1}) // {Q})::double as k, count(*) / count(distinct (src, dst // {Q})) as r, count(distinct (dst // {Q}, src // 16)) / count(*) as miss, 64.0::double as line, 4.0::double as dv, 4.0::double as di from e, nn group by n)"
add("crossover_literal", on("lineseq", lambda g: rounded(cost.crossovers(cost.measured_params(g, Q, dv=4, di=4)), "bundled")), f"{_LITSIZE} select (di + 2 * dv) / line as per_edge, round((di + 2 * dv) / line / r, 10) as bundled, miss > (di + 2 * dv) / line as per_edge_pays, miss > (di + 2 * dv) / line / r as bundled_pays from x")
add("random_access_literal", lambda s, d: cost.random_accesses(cost.CURVE.frame(s)), f"with {_LIT} select m * miss as pull, m * dv / line as per_edge, k * k as bundled from x")
add("random_access_measured", on("copurchase", lambda g: rounded(cost.random_accesses(cost.measured_params(g.persist(), Q)), "pull", "per_edge", to=4)), f"{_MEAS} select round(m * miss, 4) as pull, round(m * dv / line, 4) as per_edge, k * k as bundled from x")
add("branch_misses_literal", on("lineseq", lambda g: cost.branch_misses(cost.measured_params(g, Q, dv=4, di=4))), f"{_LITSIZE} select m as per_edge, k * k as bundled from x")
_PUB = "p as (select * from (values " + ", ".join("('%s', %s)" % (r[0], ", ".join(f"{x!r}::double" for x in r[1:])) for r in cost.PUBLISHED) + ") t(graph, n, m, t_pull, t_per_edge, t_bundled, b_pull, b_per_edge, b_bundled, bundles))"
add("speedup_literal", lambda s, d: rounded(cost.speedups(cost.published(s)), "over_per_edge", "over_pull", "gteps", to=8), f"with {_PUB} select graph, round(t_per_edge / t_bundled, 8) as over_per_edge, round(t_pull / t_bundled, 8) as over_pull, round(m / 1000 / t_bundled, 8) as gteps from p")
add("traffic_reduction_literal", lambda s, d: rounded(cost.traffic_reductions(cost.published(s)), "over_per_edge", "over_pull", "gb_per_s", "bytes_per_edge", to=8), f"with {_PUB} select graph, round(b_per_edge / b_bundled, 8) as over_per_edge, round(b_pull / b_bundled, 8) as over_pull, round(b_bundled / t_bundled, 8) as gb_per_s, round(b_bundled * 1000 / m, 8) as bytes_per_edge from p")
_MVM = f"{_PUB}, x as (select graph, b_bundled, b_pull * 1e9 as bytes, n * 1e6 as n, m * 1e6 as m, ceil(n * 1e6 / 65536) as k, m / bundles as r, 64.0::double as line, 4.0::double as dv, 4.0::double as di from p)"
add("model_vs_measured_literal", lambda s, d: rounded(cost.model_vs_measured(cost.published(s)), "model_gb", "ratio", "miss_implied", to=8), f"with {_MVM} select graph, round(({_MODEL['bundled']}) / 1e9, 8) as model_gb, b_bundled as measured_gb, round(b_bundled * 1e9 / ({_MODEL['bundled']}), 8) as ratio, round(((bytes - n * (di + dv)) / m - di) / line, 8) as miss_implied from x")


# --- user-defined functions and sketches, beside their native twins -----------------


def _expanded(s: SparkSession, d: str) -> DataFrame:
    udf.register_functions(s)
    g = wl.nation_trade(s, d)
    g.edges.groupBy("src").agg(F.collect_list("dst").alias("ids"), F.collect_list("weight").alias("ws")).createOrReplaceTempView("nation_bundles")
    return s.sql("select dst, round(sum(v), 4) as x from nation_bundles, lateral expand_bundle(2D, ids, ws) group by dst")


def _block_of_sql(s: SparkSession, d: str) -> DataFrame:
    udf.register_functions(s)
    files.register_graph(wl.line_sequence(s, d), "lines")
    return s.sql("select block_of(dst, 6) as block, count(*) as edges from lines_edges group by 1")


def _decoded(g: Graph) -> DataFrame:
    codes = layout.dest_lists(g, Q).groupBy("src").agg(F.sort_array(F.collect_list("code")).alias("codes"))
    return codes.select("src", F.array_join(F.transform(F.sort_array(udf.decode_ids("codes")), lambda x: x.cast("string")), ",").alias("dsts"))


add("udtf_expand_bundle", _expanded, f"{sql.edges('nation_trade')} select dst, round(sum(2 * weight), 4) as x from e group by 1")
add("sql_block_of", _block_of_sql, f"{sql.edges('lineseq')} select (dst >> 6) as block, count(*) as edges from e group by 1")
add("udf_decode_ids", on("lineseq", _decoded), f"{sql.edges('lineseq')} select src, {_ADJ} as dsts from e group by src")
add("gini_degree", on("cust_part", lambda g: rounded(results.gini(ga.degrees(g), "out_deg"), "gini", to=8)), f"{_EC}, d as ({_DEG}), r as (select out_deg, row_number() over (order by out_deg) as i, count(*) over () as n from d) select round(sum((2 * i - n - 1) * out_deg) / (max(n) * sum(out_deg)), 8) as gini from r")


add("udaf_gini_degree", on("cust_part", lambda g: longs(ga.degrees(g).withColumn("block", blocks.block_of("id", 256)).groupBy("block").agg(F.round(udf.gini("out_deg"), 8).alias("gini")), "block")), f"{_EC}, d as ({_DEG}), r as (select id // 256 as block, out_deg, row_number() over w as i, count(*) over (partition by id // 256) as n from d window w as (partition by id // 256 order by out_deg)) select block, coalesce(round(sum((2 * i - n - 1) * out_deg) / nullif(max(n) * sum(out_deg), 0), 8), 0.0) as gini from r group by 1")


def _two_ranks(s: SparkSession, d: str) -> DataFrame:
    g = wl.customer_part(s, d).persist()
    return rank.run(g, iters=3).withColumnRenamed("rank", "a").join(rank.run(g, "pull", iters=4).withColumnRenamed("rank", "b"), "id")


add("udaf_l1_delta", lambda s, d: longs(_two_ranks(s, d).withColumn("block", blocks.block_of("id", 256)).groupBy("block").agg(F.round(udf.l1_delta("a", "b"), 10).alias("l1")), "block"), sql.rank("cust_part", 4, final="select id // 256 as block, round(sum(abs(a.rank - b.rank)), 10) as l1 from r3 a join r4 b using (id) group by 1"))
add("l1_delta", lambda s, d: _two_ranks(s, d).agg(F.round(results.l1_delta("a", "b"), 10).alias("l1")), sql.rank("cust_part", 4, final="select round(sum(abs(a.rank - b.rank)), 10) as l1 from r3 a join r4 b using (id)"))
add("events_window_edges", lambda s, d: load_table(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp")).transform(lambda e: rounded(stream.window_counts(e).withColumn("start", F.date_format("start", "yyyy-MM-dd")), "total", to=4)), "select strftime(date_trunc('day', ts), '%Y-%m-%d') as start, event_type, count(*) as events, round(sum(value), 4) as total from events group by 1, 2")
add("events_sliding_edges", lambda s, d: load_table(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp")).transform(lambda e: rounded(stream.window_counts(e, "2 days", "1 day").withColumn("start", F.date_format("start", "yyyy-MM-dd")), "total", to=4)), "select strftime(date_trunc('day', ts) - i * interval 1 day, '%Y-%m-%d') as start, event_type, count(*) as events, round(sum(value), 4) as total from events, range(2) t(i) group by 1, 2")
add("events_session_edges", lambda s, d: load_table(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp")).transform(lambda e: stream.session_counts(e).groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("events").alias("events"))), """with g as (select user_id, ts, case when ts - lag(ts) over (partition by user_id order by ts) < interval 6 hours then 0 else 1 end as fresh from events)
    select user_id, sum(fresh)::bigint as sessions, count(*) as events from g group by 1""")


def queries() -> dict[str, Query]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(SQL)
