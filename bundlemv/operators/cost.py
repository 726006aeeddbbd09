"""Traffic and random-access models, and the counters that stand beside them."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from bundlemv.graph import Graph
from bundlemv.operators import twins
from bundlemv.operators.blocks import block_count, blocked, block_of
from bundlemv.session import materialise


@dataclass(frozen=True)
class CostParams:
    """n vertices, m edges, k blocks, r edges per bundle, miss ratio of source reads, line, value and id bytes."""

    n: float
    m: float
    k: float
    r: float = 1.0
    miss: float = 1.0
    line: float = 64
    dv: float = 4
    di: float = 4

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([tuple(float(x) for x in (self.n, self.m, self.k, self.r, self.miss, self.line, self.dv, self.di))], "n double, m double, k double, r double, miss double, line double, dv double, di double")


#: The synthetic graph of the traffic curve, in 4-byte numbers.
CURVE = CostParams(n=33.5e6, m=1070e6, k=512, r=3.06)

#: Bytes of each part of an iteration, by method, over the columns of CostParams.
PARTS = {
    ("pull", "edge_reads"): "m * (di + miss * line)",
    ("pull", "vertex_reads_writes"): "n * (di + dv)",
    ("per_edge", "scatter_read"): "n * (di + dv) + m * di",
    ("per_edge", "scatter_write"): "m * dv",
    ("per_edge", "gather_read"): "m * (di + dv)",
    ("per_edge", "final_write"): "n * dv",
    ("bundled", "scatter_read"): "m / r * di + k * k * di + n * dv",
    ("bundled", "scatter_write"): "m / r * dv",
    ("bundled", "gather_read"): "m * di + m / r * dv",
    ("bundled", "final_write"): "n * dv",
}
#: Bytes of one iteration.
MODELS = {
    "pull": "m * (di + miss * line) + n * (di + dv)",
    "per_edge": "2 * m * (di + dv) + n * (di + 2 * dv)",
    "bundled": "m * (di * (1 + 1 / r) + 2 * dv / r) + k * k * di + 2 * n * dv",
}


def model_bytes(method: str) -> Column:
    return F.expr(MODELS[method])


def models(params: DataFrame, keep: tuple[str, ...] = ()) -> DataFrame:
    """keep, method, bytes."""
    out = F.explode(F.array(*[F.struct(F.lit(m).alias("method"), model_bytes(m).alias("bytes")) for m in ("pull", "per_edge", "bundled")]))
    return params.select(*keep, out.alias("x")).select(*keep, "x.method", "x.bytes")


def parts(params: DataFrame) -> DataFrame:
    """method, part, bytes: the addends of the models."""
    out = F.explode(F.array(*[F.struct(F.lit(m).alias("method"), F.lit(p).alias("part"), F.expr(c).alias("bytes")) for (m, p), c in PARTS.items()]))
    return params.select(out.alias("x")).select("x.*")


def limits(params: DataFrame) -> DataFrame:
    """One row: best and worst traffic of pull and bundled, best miss ratio and best r."""
    return params.selectExpr(
        "m * di as pull_best", "m * (di + line) as pull_worst", "m * di as bundled_best", "m * (2 * di + 2 * dv) as bundled_worst",
        "n * dv / (m * line) as miss_best", "m / n as r_best",
    )


def crossovers(params: DataFrame) -> DataFrame:
    """One row: miss ratios above which the two scatter methods move less than pulling."""
    per_edge = "(di + 2 * dv) / line"
    return params.selectExpr(f"{per_edge} as per_edge", f"{per_edge} / r as bundled", f"miss > {per_edge} as per_edge_pays", f"miss > {per_edge} / r as bundled_pays")


def random_accesses(params: DataFrame) -> DataFrame:
    """One row: random accesses of an iteration, by method."""
    return params.selectExpr("m * miss as pull", "m * dv / line as per_edge", "k * k as bundled")


def branch_misses(params: DataFrame) -> DataFrame:
    """One row: data-dependent branches that may be mispredicted: a buffer test per edge against a switch per block pair."""
    return params.selectExpr("m as per_edge", "k * k as bundled")


def curve(params: DataFrame, rs: list[float]) -> DataFrame:
    """r, bytes: the bundled model as r grows."""
    return params.drop("r").withColumn("r", F.explode(F.array(*map(F.lit, rs)))).select("r", model_bytes("bundled").alias("bytes"))


def implied_miss(rows: DataFrame) -> DataFrame:
    """miss_implied for rows with n, m, line, dv, di and measured pull bytes."""
    return rows.withColumn("miss_implied", F.expr("((bytes - n * (di + dv)) / m - di) / line"))


# --- measured -------------------------------------------------------------------


def compression_ratio(g: Graph, q: int, approx: bool = False, rsd: float = 0.02) -> DataFrame:
    """One row: m, bundles, r. ``approx`` sketches the bundles and shuffles no pairs."""
    pairs = blocked(g, q)
    if approx:
        own = pairs.agg(F.count("*").alias("m"), F.approx_count_distinct(F.struct("src", "dst_block"), rsd).alias("bundles"))
    else:
        own = pairs.groupBy("src", "dst_block").agg(F.count("*").alias("e")).agg(F.sum("e").alias("m"), F.count("*").alias("bundles"))
    return own.select("m", "bundles", (F.col("m") / F.col("bundles")).alias("r"))


def compression_by_width(g: Graph, shifts: list[int]) -> DataFrame:
    """shift, q, k, m, bundles, r for many widths from one scan."""
    each = g.edges.select("src", F.explode(F.array(*map(F.lit, shifts))).alias("shift"), "dst").select("shift", "src", F.expr("shiftright(dst, shift)").alias("b"))
    own = each.groupBy("shift", "src", "b").agg(F.count("*").alias("e")).groupBy("shift").agg(F.sum("e").alias("m"), F.count("*").alias("bundles"))
    q = F.expr("shiftleft(1L, shift)")
    return own.select(F.col("shift").cast("long").alias("shift"), q.alias("q"), F.ceil(F.lit(g.n) / q).cast("long").alias("k"), "m", "bundles", (F.col("m") / F.col("bundles")).alias("r"))


def count_messages(g: Graph, q: int, dv: int = 8, di: int = 8) -> DataFrame:
    """method, messages, bytes of one iteration's scatter: values, and ids where they travel."""
    own = compression_ratio(g, q)
    rows = F.explode(F.array(*[F.struct(F.lit(name).alias("method"), F.col(c).alias("messages"), (F.col(c) * size).cast("long").alias("bytes")) for name, c, size in (
        ("per_edge", "m", dv), ("per_edge_resend", "m", dv + di), ("bundled", "bundles", dv), ("edge_scan", "m", dv + di),
    )] + [F.struct(F.lit("bundled_resend").alias("method"), F.col("bundles").alias("messages"), (F.col("bundles") * dv + F.col("m") * di).cast("long").alias("bytes")), F.struct(F.lit("pull").alias("method"), F.lit(0).cast("long").alias("messages"), F.lit(0).cast("long").alias("bytes"))]))
    return own.select(rows.alias("x")).select("x.*")


def count_bin_switches(g: Graph, q: int) -> DataFrame:
    """method, switches: how often the written bin changes within source blocks, in each method's order."""
    own = blocked(g, q)
    edge_order = Window.partitionBy("src_block").orderBy("src", "dst")
    changed = F.coalesce(F.lag("dst_block").over(edge_order) != F.col("dst_block"), F.lit(True)).cast("long")
    edges = own.withColumn("c", changed).agg(F.sum("c").alias("switches")).select(F.lit("per_edge").alias("method"), "switches")
    layout = own.select("src_block", "dst_block", "src").distinct()
    layout_order = Window.partitionBy("src_block").orderBy("dst_block", "src")
    runs = layout.withColumn("c", F.coalesce(F.lag("dst_block").over(layout_order) != F.col("dst_block"), F.lit(True)).cast("long")).agg(F.sum("c").alias("switches"))
    return edges.union(runs.select(F.lit("bundled").alias("method"), "switches"))


def nonempty_pairs(g: Graph, q: int) -> DataFrame:
    """One row: pairs of blocks with edges, all pairs."""
    k = block_count(g.n, q)
    return blocked(g, q).select("src_block", "dst_block").distinct().agg(F.count("*").alias("pairs")).select("pairs", F.lit(k * k).cast("long").alias("most"))


def est_miss_ratio(g: Graph, q: int, line: int = 64, dv: int = 8) -> DataFrame:
    """One row: distinct lines of sources that the destinations of a block read, over edges; stands in for a hardware counter."""
    own = g.edges.select(block_of("dst", q).alias("b"), F.floor(F.col("src") / (line // dv)).alias("l"))
    return own.groupBy("b", "l").agg(F.count("*").alias("e")).agg(F.count("*").alias("lines"), F.sum("e").alias("m")).select("lines", (F.col("lines") / F.col("m")).alias("miss"))


def memory_footprint(g: Graph, q: int, dv: int = 8, di: int = 8) -> DataFrame:
    """One row: bytes of value bins, id bins, layout, and of offsets with and without the block layout."""
    k = block_count(g.n, q)
    return compression_ratio(g, q).select(
        (F.col("bundles") * dv).alias("value_bins"), (F.col("m") * di).alias("id_bins"), (F.col("bundles") * di).alias("layout"),
        F.lit(k * k * di).cast("long").alias("offsets"), F.lit(g.n * k * di).cast("long").alias("offsets_plain"))


def measured_params(g: Graph, q: int, line: int = 64, dv: int = 8, di: int = 8) -> DataFrame:
    """Columns of the models from counters of a graph."""
    r = compression_ratio(g, q).select(F.col("m").cast("double").alias("m"), "r")
    miss = est_miss_ratio(g, q, line, dv).select("miss")
    one = F.lit(1).alias("one")
    return _params(r.select("*", one).join(miss.select("*", one), "one"), g, q, line, dv, di)


def _params(both: DataFrame, g: Graph, q: int, line: int, dv: int, di: int) -> DataFrame:
    return both.select(F.lit(float(g.n)).alias("n"), "m", F.lit(float(block_count(g.n, q))).alias("k"), "r", "miss", F.lit(float(line)).alias("line"), F.lit(float(dv)).alias("dv"), F.lit(float(di)).alias("di"))


def labelled_compression(g: Graph, perm: DataFrame, q: int) -> DataFrame:
    """``compression_ratio`` under a labeling (old, new); by classes of twins where the graph has them."""
    from bundlemv.operators.labels import relabel

    if g.twins is None:
        return compression_ratio(relabel(g, perm), q)
    return twins.compression(g.twins, twins.near_blocks(g.twins, perm, q))


def labelled_params(g: Graph, perm: DataFrame, q: int, line: int = 64, dv: int = 8, di: int = 8) -> DataFrame:
    """``measured_params`` under a labeling (old, new); by classes of twins where the graph has them."""
    from bundlemv.operators.labels import relabel

    if g.twins is None or q % (line // dv):
        return measured_params(relabel(g, perm).persist(), q, line, dv, di)
    near = materialise(twins.near_blocks(g.twins, perm, q), "near-blocks")
    r = twins.compression(g.twins, near)
    both = r.crossJoin(twins.met_lines(g.twins, near, perm, q, line // dv)).withColumn("miss", F.col("lines") / F.col("m"))
    return _params(both.select(F.col("m").cast("double").alias("m"), "r", "miss"), g, q, line, dv, di)


def traffic_by_label(g: Graph, perms: dict[str, DataFrame], q: int) -> DataFrame:
    """label, method, r, bytes: the models on what each labeling measures."""
    out = None
    for name, perm in perms.items():
        own = models(labelled_params(g, perm, q), keep=("r",)).select(F.lit(name).alias("label"), "method", "r", "bytes")
        out = own if out is None else out.union(own)
    return out


def traffic_by_width(g: Graph, shifts: list[int], dv: int = 8, di: int = 8, cache: int = 256 << 10) -> DataFrame:
    """shift, q, k, r, per_edge, bundled (bytes), block_bytes, overflow (bytes of a block's values that a cache does not hold)."""
    own = compression_by_width(g, shifts).withColumns({"n": F.lit(float(g.n)), "dv": F.lit(float(dv)), "di": F.lit(float(di))})
    size = F.col("q") * dv
    return own.select("shift", "q", "k", "r", model_bytes("per_edge").alias("per_edge"), model_bytes("bundled").alias("bundled"), size.alias("block_bytes"), F.greatest(F.lit(0).cast("long"), size - cache).alias("overflow"))


# --- published figures ------------------------------------------------------------

# Graph, nodes and edges in millions; seconds per iteration of pull, per-edge and
# bundled; GB per iteration of the same three; bundles in millions.
PUBLISHED = [
    ("gplus", 28.94, 462.99, 0.44, 0.38, 0.16, 13.1, 9.3, 6.6, 243.8),
    ("pld", 42.89, 623.06, 0.68, 0.48, 0.22, 24.5, 12.6, 9.4, 347.7),
    ("web", 118.14, 992.84, 0.21, 0.81, 0.21, 7.5, 21.6, 8.5, 118.1),
    ("kron", 33.5, 1047.93, 0.65, 0.72, 0.25, 18.1, 19.9, 10.4, 342.7),
    ("twitter", 61.58, 1468.36, 1.83, 1.11, 0.45, 68.2, 28.8, 19.4, 722.4),
    ("sd1", 94.95, 1937.49, 1.97, 1.49, 0.59, 65.1, 37.8, 26.9, 976.9),
]
PUBLISHED_SCHEMA = "graph string, n double, m double, t_pull double, t_per_edge double, t_bundled double, b_pull double, b_per_edge double, b_bundled double, bundles double"


def published(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(PUBLISHED, PUBLISHED_SCHEMA)


def speedups(rows: DataFrame) -> DataFrame:
    """graph, speedup over per-edge and over pull, GTEPS of bundled."""
    return rows.select("graph", (F.col("t_per_edge") / F.col("t_bundled")).alias("over_per_edge"), (F.col("t_pull") / F.col("t_bundled")).alias("over_pull"), (F.col("m") / 1000 / F.col("t_bundled")).alias("gteps"))


def traffic_reductions(rows: DataFrame) -> DataFrame:
    return rows.select("graph", (F.col("b_per_edge") / F.col("b_bundled")).alias("over_per_edge"), (F.col("b_pull") / F.col("b_bundled")).alias("over_pull"), (F.col("b_bundled") / F.col("t_bundled")).alias("gb_per_s"), (F.col("b_bundled") * 1000 / F.col("m")).alias("bytes_per_edge"))


def model_vs_measured(rows: DataFrame, width: int = 65536) -> DataFrame:
    """graph, modelled and measured GB of bundled, their ratio, and the miss ratio that pulling implies."""
    p = rows.select("graph", "b_bundled", "b_pull", (F.col("n") * 1e6).alias("n"), (F.col("m") * 1e6).alias("m"), F.ceil(F.col("n") * 1e6 / width).cast("double").alias("k"), (F.col("m") / F.col("bundles")).alias("r"),
                    F.lit(1.0).alias("miss"), F.lit(64.0).alias("line"), F.lit(4.0).alias("dv"), F.lit(4.0).alias("di"))
    p = implied_miss(p.withColumn("bytes", F.col("b_pull") * 1e9))
    return p.select("graph", (model_bytes("bundled") / 1e9).alias("model_gb"), F.col("b_bundled").alias("measured_gb"), (F.col("b_bundled") * 1e9 / model_bytes("bundled")).alias("ratio"), "miss_implied")
