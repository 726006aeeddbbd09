"""Blocks: contiguous ranges of ids, and ways to choose them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from bundlemv.graph import Graph, degrees

#: Bytes of a vertex value.
VALUE_BYTES = 8


def block_of(col: str | Column, q: int) -> Column:
    """Block of an id for width q: a shift for powers of two, else a division."""
    col = F.col(col) if isinstance(col, str) else col
    if q < 1:
        raise ValueError("a block holds at least one id")
    return (F.shiftright(col, q.bit_length() - 1) if q & (q - 1) == 0 else F.floor(col / q)).cast("int")


def assign_blocks(df: DataFrame, col: str, q: int, out: str = "block") -> DataFrame:
    return df.withColumn(out, block_of(col, q))


def block_count(n: int, q: int) -> int:
    return -(-n // q)


def blocked(g: Graph, q: int) -> DataFrame:
    """Edges with src_block and dst_block."""
    return g.edges.withColumn("src_block", block_of("src", q)).withColumn("dst_block", block_of("dst", q))


def parts_of(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def place(df: DataFrame, *cols: str) -> DataFrame:
    """Deal rows by block columns; the number of parts is stated, so both sides of later joins agree."""
    return df.repartition(parts_of(df.sparkSession), *cols)


def block_table(g: Graph, q: int) -> DataFrame:
    """block, first, last, vertices, out_edges, in_edges."""
    own = assign_blocks(degrees(g), "id", q)
    return own.groupBy("block").agg(F.min("id").alias("first"), F.max("id").alias("last"), F.count("*").alias("vertices"), F.sum("out_deg").alias("out_edges"), F.sum("in_deg").alias("in_edges"))


def block_matrix(g: Graph, q: int) -> DataFrame:
    """src_block, dst_block, edges, bundles of the block pairs with edges; the pre-aggregation is by source, so hubs spread."""
    per = blocked(g, q).groupBy("src_block", "dst_block", "src").agg(F.count("*").alias("e"))
    return per.groupBy("src_block", "dst_block").agg(F.sum("e").alias("edges"), F.count("*").alias("bundles"))


def block_matrix_cube(g: Graph, q: int) -> DataFrame:
    """Edges by block pair with all totals; -1 stands for "all"."""
    cube = blocked(g, q).cube("src_block", "dst_block").agg(F.count("*").alias("edges"), F.grouping("src_block").alias("a"), F.grouping("dst_block").alias("b"))
    return cube.select(F.when(F.col("a") == 1, -1).otherwise(F.col("src_block")).alias("src_block"), F.when(F.col("b") == 1, -1).otherwise(F.col("dst_block")).alias("dst_block"), "edges")


def block_matrix_rollup(g: Graph, q: int) -> DataFrame:
    """Edges by block pair, by source block, and in all; -1 stands for "all"."""
    own = blocked(g, q).rollup("src_block", "dst_block").agg(F.count("*").alias("edges"))
    return own.select(F.coalesce("src_block", F.lit(-1)).alias("src_block"), F.coalesce("dst_block", F.lit(-1)).alias("dst_block"), "edges")


def block_totals(g: Graph, q: int) -> DataFrame:
    """Edges by source block and by destination block, in one pass by grouping sets; -1 stands for "all"."""
    own = blocked(g, q).groupingSets([["src_block"], ["dst_block"]], "src_block", "dst_block").agg(F.count("*").alias("edges"))
    return own.select(F.coalesce("src_block", F.lit(-1)).alias("src_block"), F.coalesce("dst_block", F.lit(-1)).alias("dst_block"), "edges")


def block_pivot(g: Graph, q: int, k: int) -> DataFrame:
    """The matrix as k columns, for few blocks."""
    wide = blocked(g, q).groupBy("src_block").pivot("dst_block", list(range(k))).count()
    return wide.select("src_block", *[F.coalesce(F.col(str(i)), F.lit(0)).alias(f"to_{i}") for i in range(k)])


def plan_width(n: int, task_bytes: int, tasks: int, value_bytes: int = VALUE_BYTES) -> int:
    """The largest power of two whose block of values fits ``task_bytes``, but so that ``tasks`` blocks exist."""
    most = max(1, task_bytes // value_bytes)
    fair = max(1, n // max(1, tasks))
    return 1 << (min(most, fair).bit_length() - 1)


def width_for(g: Graph, task_bytes: int = 32 << 20) -> int:
    """A width for this session: about two blocks for each part that a shuffle makes, as wide blocks bundle more."""
    return plan_width(max(g.n, 1), task_bytes, 2 * parts_of(g.spark))


def custom_blocks(ids: DataFrame, block: Column) -> DataFrame:
    """old, new: a relabeling that makes the given blocks contiguous. Places come per block, offsets from the blocks' counts."""
    own = ids.select(F.col("id").alias("old"), block.alias("b"))
    before = Window.orderBy("b").rowsBetween(Window.unboundedPreceding, -1)
    base = own.groupBy("b").agg(F.count("*").alias("c")).select("b", F.coalesce(F.sum("c").over(before), F.lit(0)).alias("base"))  # a row per block
    inside = F.row_number().over(Window.partitionBy("b").orderBy("old")) - 1
    return own.withColumn("i", inside).join(base, "b").select("old", (F.col("base") + F.col("i")).alias("new"))


def balanced_blocks(g: Graph, k: int, stripe: int = 4096) -> DataFrame:
    """id, block: contiguous blocks of nearly equal out-edges.

    The running sum of degrees is taken in stripes of ids and then over the stripes.
    """
    own = degrees(g).select("id", "out_deg", F.floor(F.col("id") / stripe).alias("s"))
    before = Window.orderBy("s").rowsBetween(Window.unboundedPreceding, -1)
    base = own.groupBy("s").agg(F.sum("out_deg").alias("c")).select("s", F.coalesce(F.sum("c").over(before), F.lit(0)).alias("base"))
    inside = F.coalesce(F.sum("out_deg").over(Window.partitionBy("s").orderBy("id").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    ahead = own.withColumn("inside", inside).join(base, "s").select("id", "out_deg", (F.col("base") + F.col("inside")).alias("ahead"))
    return ahead.select("id", "out_deg", F.least(F.lit(k - 1), F.floor(F.col("ahead") * k / F.lit(max(1, g.m)))).cast("int").alias("block"))


def bounds(blocks: DataFrame) -> DataFrame:
    """block, lo, hi of contiguous blocks."""
    return blocks.groupBy("block").agg(F.min("id").alias("lo"), F.max("id").alias("hi"))


def by_bounds(ids: DataFrame, limits: DataFrame, k: int) -> DataFrame:
    """Range join of ids to blocks by (block, lo, hi); the k rows of bounds are broadcast."""
    if k > 100_000:
        raise ValueError("bounds of more than 100000 blocks are not broadcast")
    return ids.join(F.broadcast(limits), F.col("id").between(F.col("lo"), F.col("hi"))).select("id", "block")
