"""Graphs and matrices built from the given tables."""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from bundlemv.graph import Graph, Matrix, contract, dense_ids, make_graph
from bundlemv.operators.blocks import place
from bundlemv.operators.twins import Twins, fold, pairs
from bundlemv.sources.tables import load_table

#: A total order of an order's lines.
LINE_ORDER = ["l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice"]
#: kNN holds so many broadcast vectors against so many rows at once.
KNN_BLOCK, KNN_CHUNK = 4096, 1024


def _pairs(rows: DataFrame, group: str, member: str, by_src: bool = False) -> DataFrame:
    """Distinct ordered pairs of different members that share a group, from one shuffle by group and one of the pairs.

    With ``by_src`` pairs lie by their first member, so what counts by it deals none again; copies
    are then merged only where they meet.
    """
    met = F.collect_set(member).over(Window.partitionBy(group))
    own = rows.where(F.col(group).isNotNull()).select(F.col(member).alias("src"), met.alias("met"))
    own = own.select("src", F.array_remove("met", F.col("src")).alias("met")).where("size(met) > 0")  # a row for several pairs
    return (place(own, "src") if by_src else own).select("src", F.explode("met").alias("dst")).distinct()


def copurchase(spark: SparkSession, sf_dir: str) -> Graph:
    """Part to part in a common order."""
    return Graph(_pairs(load_table(spark, sf_dir, "lineitem"), "l_orderkey", "l_partkey", by_src=True), load_table(spark, sf_dir, "part").count())


def supplier_mesh(spark: SparkSession, sf_dir: str) -> Graph:
    """Supplier to supplier in a common order."""
    return Graph(_pairs(load_table(spark, sf_dir, "lineitem"), "l_orderkey", "l_suppkey"), load_table(spark, sf_dir, "supplier").count())


def line_sequence(spark: SparkSession, sf_dir: str) -> Graph:
    """Part to the next part of its order."""
    lines = load_table(spark, sf_dir, "lineitem")
    after = F.lead("l_partkey").over(Window.partitionBy("l_orderkey").orderBy(*LINE_ORDER))
    pairs = lines.select(F.col("l_partkey").alias("src"), after.alias("dst")).where("dst is not null and src <> dst")
    return make_graph(pairs, load_table(spark, sf_dir, "part").count())


def order_line(spark: SparkSession, sf_dir: str, label: str = "order") -> Matrix:
    """Order to the places of its lines, numbered by order, ship date or part: labels of high or low locality."""
    first = {"order": ["l_orderkey"], "shipdate": ["l_shipdate", "l_orderkey"], "part": ["l_partkey", "l_orderkey"]}[label]
    lines = load_table(spark, sf_dir, "lineitem").select("l_orderkey", "l_shipdate", *LINE_ORDER)
    placed = dense_ids(lines, [*first, *LINE_ORDER], "j")
    return Matrix(placed.select(F.col("l_orderkey").alias("i"), "j", F.lit(1.0).alias("w")), load_table(spark, sf_dir, "orders").count(), lines.count())


def customer_part(spark: SparkSession, sf_dir: str) -> Graph:
    """Customer to the parts that it ordered, behind the customers' ids; parts are sinks."""
    customers = load_table(spark, sf_dir, "customer").count()
    lines = load_table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"), "l_partkey")
    bought = load_table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey").join(lines, "o_orderkey")
    pairs = bought.select(F.col("o_custkey").alias("src"), (F.col("l_partkey") + customers).alias("dst"))
    return make_graph(pairs, customers + load_table(spark, sf_dir, "part").count())


def next_in_time(events: DataFrame) -> DataFrame:
    """user_id with the user of the next event by (ts, event_id): windows per day, stitched from day to day."""
    rows = events.select("ts", "event_id", "user_id", F.date_trunc("day", "ts").alias("day"))
    inside = Window.partitionBy("day").orderBy("ts", "event_id")
    key = F.struct("ts", "event_id", "user_id")
    days = rows.groupBy("day").agg(F.min(key)["user_id"].alias("head"), F.max(key)["user_id"].alias("tail"))
    stitched = days.select(F.col("tail").alias("src"), F.lead("head").over(Window.orderBy("day")).alias("dst"))  # a row per day
    return rows.select(F.col("user_id").alias("src"), F.lead("user_id").over(inside).alias("dst")).union(stitched).where("dst is not null")


def user_flow(spark: SparkSession, sf_dir: str) -> Graph:
    """User of an event to the user of the next event."""
    events = load_table(spark, sf_dir, "events")
    n = events.agg(F.max("user_id")).first()[0] + 1
    return make_graph(next_in_time(events).where("src <> dst"), n)


def page_paths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """page_id, path: distinct link targets of each page."""
    pages = load_table(spark, sf_dir, "pages")
    return pages.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("path")).distinct()


def page_links(spark: SparkSession, sf_dir: str) -> Graph:
    """Page to page that share a link target, listed by classes of pages with the same targets. The graph folds to them, if its ids are 0 .. n-1."""
    pages, paths = load_table(spark, sf_dir, "pages"), page_paths(spark, sf_dir)
    n, shared = pages.count(), paths.select(F.col("page_id").alias("id"), F.col("path").alias("key"))

    def twins() -> Twins | None:
        ids = pages.agg(F.count_distinct("page_id").alias("c"), F.min("page_id").alias("lo"), F.max("page_id").alias("hi")).first()
        if (ids.c, ids.lo, ids.hi) != (n, 0, n - 1):
            return None
        return fold(shared, spark.range(n), n)

    return Graph(pairs(shared), n, twins)


def page_anchor(spark: SparkSession, sf_dir: str) -> Graph:
    """Page to its link targets, behind the pages' ids; targets are never crawled and so are sinks."""
    own, n = page_paths(spark, sf_dir), load_table(spark, sf_dir, "pages").count()
    names = dense_ids(own.select("path").distinct(), ["path"], "place")
    edges = own.join(names, "path").select(F.col("page_id").alias("src"), (F.col("place") + n).alias("dst"))
    return Graph(edges, n + names.count())


def hosts(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, int]:
    """(page to host as old, new; number of hosts), hosts numbered by name."""
    own = load_table(spark, sf_dir, "pages").select(F.col("page_id").alias("old"), F.regexp_extract("url", "://([^/:?#]+)", 1).alias("host"))
    names = dense_ids(own.select("host").distinct(), ["host"], "new")
    return own.join(names, "host").select("old", "new"), names.count()


def host_links(spark: SparkSession, sf_dir: str) -> Graph:
    """Page links between hosts, weighted by their number."""
    return contract(page_links(spark, sf_dir), *hosts(spark, sf_dir))


def nation_trade(spark: SparkSession, sf_dir: str) -> Graph:
    """Customer's nation to supplier's nation, weighted by revenue."""
    t = lambda name: load_table(spark, sf_dir, name)
    lines = t("lineitem").select(F.col("l_orderkey").alias("o_orderkey"), F.col("l_suppkey").alias("s_suppkey"), (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("v"))
    all_ = (
        lines.join(t("orders").select("o_orderkey", F.col("o_custkey").alias("c_custkey")), "o_orderkey")
        .join(t("customer").select("c_custkey", F.col("c_nationkey").cast("long").alias("src")), "c_custkey")
        .join(t("supplier").select("s_suppkey", F.col("s_nationkey").cast("long").alias("dst")), "s_suppkey")
    )
    return Graph(all_.groupBy("src", "dst").agg(F.round(F.sum("v"), 4).alias("weight")), t("nation").count())


def knn(spark: SparkSession, sf_dir: str, k: int = 8, block: int = KNN_BLOCK) -> Graph:
    """Vector to its k nearest by cosine, weighted by the cosine rounded to 6 places; ties to smaller ids.

    All pairs are compared: blocks of vectors are broadcast, each partition keeps the k
    nearest of its rows, and a sort per vector merges them.
    """
    rows = load_table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    n = rows.count()
    blocks = max(1, -(-n // block))

    def parts(t):
        ids, x = t.column(0).to_numpy(), t.column(1).flatten().to_numpy().astype(np.float64).reshape(t.num_rows, -1)
        return ids, x / np.sqrt((x**2).sum(1))[:, None]

    def nearest(held):
        def work(batches):
            ids, q = held.value
            own, dst, cos = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
            worst = np.full(len(ids), -np.inf)
            for b in batches:
                for i in range(0, b.num_rows, KNN_CHUNK):
                    to, x = parts(b.slice(i, KNN_CHUNK))
                    c = np.round(q @ x.T, 6)
                    c[ids[:, None] == to[None, :]] = -np.inf
                    few = min(k, len(to))
                    least = np.maximum(np.partition(c, -few, axis=1)[:, -few], worst)
                    r, j = np.nonzero((c >= least[:, None]) & (c > -np.inf))
                    own, dst, cos = np.concatenate([own, r]), np.concatenate([dst, to[j]]), np.concatenate([cos, c[r, j]])
                    order = np.lexsort((dst, -cos, own))
                    own, dst, cos = own[order], dst[order], cos[order]
                    place = np.arange(len(own)) - np.searchsorted(own, own)
                    own, dst, cos, place = (v[place < k] for v in (own, dst, cos, place))
                    worst[own[place == k - 1]] = cos[place == k - 1]
            yield pa.RecordBatch.from_arrays([pa.array(ids[own]), pa.array(dst), pa.array(cos)], names=["src", "dst", "weight"])

        return work

    found = []
    for i in range(blocks):
        mine = rows.where(F.pmod(F.xxhash64("vec_id"), F.lit(blocks)) == i).toArrow().combine_chunks()
        if mine.num_rows:
            held = spark.sparkContext.broadcast(parts(mine.to_batches()[0]))
            found.append(rows.mapInArrow(nearest(held), "src long, dst long, weight double"))
    if not found:
        return Graph(spark.createDataFrame([], "src long, dst long, weight double"), n)
    order = Window.partitionBy("src").orderBy(F.desc("weight"), "dst")
    best = reduce(DataFrame.unionAll, found).withColumn("r", F.row_number().over(order)).where(F.col("r") <= k)
    return Graph(best.select("src", "dst", "weight"), n)


def part_supplier(spark: SparkSession, sf_dir: str) -> Matrix:
    """Part x supplier: quantities."""
    w = load_table(spark, sf_dir, "lineitem").groupBy(F.col("l_partkey").alias("i"), F.col("l_suppkey").alias("j")).agg(F.sum("l_quantity").alias("w"))
    return Matrix(w, load_table(spark, sf_dir, "part").count(), load_table(spark, sf_dir, "supplier").count())


# --- synthetic ------------------------------------------------------------------


def kronecker(spark: SparkSession, scale: int, edge_factor: int = 16, seeds: DataFrame | None = None) -> Graph:
    """A skewed random graph of 2**scale vertices: each level of an edge picks a quadrant by a congruential generator. seeds: ids that start the generator, an edge each."""
    rows = (spark.range(edge_factor << scale) if seeds is None else seeds).select(((F.col("id") * 2654435761 + 12345) % 2147483647).alias("st"), F.lit(0).cast("long").alias("src"), F.lit(0).cast("long").alias("dst"))

    def level(acc, _):
        at = acc["st"] % 10000
        down, right = (at >= 7600).cast("long"), (((at >= 5700) & (at < 7600)) | (at >= 9500)).cast("long")
        return F.struct((acc["st"] * 48271 % 2147483647).alias("st"), (acc["src"] * 2 + down).alias("src"), (acc["dst"] * 2 + right).alias("dst"))

    walked = rows.select(F.aggregate(F.sequence(F.lit(1), F.lit(scale)), F.struct("st", "src", "dst"), level).alias("e"))
    return make_graph(walked.select("e.src", "e.dst"), 1 << scale)


def banded(spark: SparkSession, n: int, band: int) -> Graph:
    """Each vertex to the next ``band``: perfect locality."""
    steps = F.explode(F.sequence(F.col("id") + 1, F.least(F.col("id") + band, F.lit(n - 1))))
    return Graph(spark.range(n - 1).select(F.col("id").alias("src"), steps.alias("dst")), n)


#: The worked example: nine vertices in three blocks of three.
WORKED9 = [(2, 6), (2, 7), (4, 3), (4, 5), (6, 3), (6, 4), (7, 0), (7, 2), (8, 1), (8, 7)]


def worked9(spark: SparkSession) -> Graph:
    return Graph(spark.createDataFrame(WORKED9, "src long, dst long"), 9)


# --- the same forms over given tables -------------------------------------------


def kronecker_orders(spark: SparkSession, sf_dir: str, scale: int = 10) -> Graph:
    """The skewed graph with an edge for each order."""
    return kronecker(spark, scale, seeds=load_table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("id")))


def banded_parts(spark: SparkSession, sf_dir: str, band: int = 8) -> Graph:
    """Each part to those of the next ``band`` keys that exist."""
    parts = load_table(spark, sf_dir, "part").select(F.col("p_partkey").alias("src"))
    steps = parts.select("src", F.explode(F.sequence(F.col("src") + 1, F.col("src") + band)).alias("dst"))
    return Graph(steps.join(parts.withColumnRenamed("src", "dst"), "dst", "left_semi").select("src", "dst"), parts.count())


def nine_groups(spark: SparkSession, sf_dir: str) -> Graph:
    """Nine groups of parts, three blocks of three: a group to those of the parts that follow its own in an order."""
    e = line_sequence(spark, sf_dir).edges.select((F.col("src") % 9).alias("src"), (F.col("dst") % 9).alias("dst"))
    return make_graph(e.where("src <> dst"), 9)


def user_flow_loops(spark: SparkSession, sf_dir: str) -> Graph:
    """``user_flow`` with the loops of users who follow themselves."""
    events = load_table(spark, sf_dir, "events")
    return make_graph(next_in_time(events), events.agg(F.max("user_id")).first()[0] + 1)
