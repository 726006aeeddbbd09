"""Edge lists and adjacency texts as sources; layouts and ranks as sinks."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, LongType, StructField, StructType

from bundlemv.graph import Graph
from bundlemv.operators.blocks import block_count, place
from bundlemv.operators.layout import Packed, packed_pairs
from bundlemv.operators.rank import Prepared, vertex_table
from bundlemv.operators.steps import allow_placement, bundled_on

_FORMATS = {"csv": ("csv", ","), "tsv": ("csv", "\t"), "ssv": ("csv", " "), "json": ("json", None), "parquet": ("parquet", None), "orc": ("orc", None)}


def read_edges(spark: SparkSession, path: str, fmt: str = "csv", src: str = "src", dst: str = "dst", weight: str | None = None, header: bool = False, comment: str | None = "#") -> DataFrame:
    """src, dst[, weight] from an edge list with a stated schema; rows without two ids are refused when read."""
    if fmt not in _FORMATS:
        raise ValueError(f"formats are {sorted(_FORMATS)}")
    kind, sep = _FORMATS[fmt]
    fields = [StructField(src, LongType()), StructField(dst, LongType())] + ([StructField(weight, DoubleType())] if weight else [])
    reader = spark.read.format(kind)
    if sep is not None:
        reader = reader.option("sep", sep).option("header", header).option("mode", "FAILFAST")
        if comment:
            reader = reader.option("comment", comment)
    rows = reader.schema(StructType(fields)).load(path)
    return rows.select(F.col(src).alias("src"), F.col(dst).alias("dst"), *([F.col(weight).alias("weight")] if weight else []))


def read_adjacency(spark: SparkSession, path: str) -> DataFrame:
    """src, dst from lines "src d1 d2 ..."; blank lines and lines that start with # are passed over."""
    lines = spark.read.text(path).where("length(trim(value)) > 0 and not startswith(trim(value), '#')")
    ids = lines.select(F.transform(F.split(F.trim("value"), r"\s+"), lambda x: x.cast("long")).alias("ids"))
    return ids.select(F.col("ids")[0].alias("src"), F.explode(F.slice("ids", 2, F.greatest(F.size("ids") - 1, F.lit(0)))).alias("dst"))


def write_adjacency(g: Graph, path: str) -> None:
    per = g.edges.groupBy("src").agg(F.sort_array(F.collect_list("dst")).alias("d"))
    per.select(F.concat_ws(" ", F.col("src").cast("string"), F.array_join(F.transform("d", lambda x: x.cast("string")), " ")).alias("value")).write.text(path)


def write_layout(g: Graph, path: str, q: int) -> None:
    """The packed layout and lists as Parquet, parted by block, the vertices, and their numbers beside them: built once, for any later run."""
    p = packed_pairs(g, q)
    p.lists.drop("srcs").write.parquet(f"{path}/lists")
    p.layout.write.parquet(f"{path}/layout")
    for df in (p.lists, p.layout):
        df.unpersist()
    vertex_table(g, q).write.parquet(f"{path}/vertices")
    m = g.spark.read.parquet(f"{path}/lists").agg(F.sum(F.size("ids"))).first()[0]
    b = g.spark.read.parquet(f"{path}/layout").agg(F.sum(F.size("srcs"))).first()[0]
    meta = {"n": g.n, "m": m or 0, "q": q, "k": block_count(g.n, q), "bundles": b or 0, "weighted": g.weighted, "chunked": p.chunked}
    g.spark.createDataFrame([(json.dumps(meta),)], "value string").coalesce(1).write.text(f"{path}/meta")


def open_layout(spark: SparkSession, path: str) -> tuple[dict, DataFrame, DataFrame]:
    """(numbers, layout, lists) of a written layout; raises if they do not fit together."""
    meta = json.loads(spark.read.text(f"{path}/meta").first().value)
    layout, lists = spark.read.parquet(f"{path}/layout"), spark.read.parquet(f"{path}/lists")
    values = layout.agg(F.sum(F.size("srcs"))).first()[0] or 0
    ids = lists.agg(F.sum(F.size("ids"))).first()[0] or 0
    if (values, ids) != (meta["bundles"], meta["m"]):
        raise ValueError(f"{path} holds {values} values and {ids} ids; its numbers say {meta['bundles']} and {meta['m']}")
    return meta, layout, lists


def prepared_layout(spark: SparkSession, path: str) -> Prepared:
    """What ``rank.run(None, prepared=...)`` runs on: the written rows are dealt to this session's parts; edges are neither read nor sorted again."""
    allow_placement(spark)
    meta, layout, lists = open_layout(spark, path)
    p = Packed(layout, lists, meta["q"], meta["weighted"], meta["chunked"]).placed()
    vertices = place(spark.read.parquet(f"{path}/vertices"), "block").sortWithinPartitions("block", "id").persist()
    return Prepared(meta["n"], meta["q"], vertices, bundled_on(p))


def write_ranks(ranks: DataFrame, path: str, mode: str = "errorifexists") -> None:
    ranks.write.mode(mode).parquet(path)


def register_graph(g: Graph, name: str) -> None:
    """Temporary views <name>_edges and <name>_vertices for SQL."""
    g.edges.createOrReplaceTempView(f"{name}_edges")
    g.vertices.createOrReplaceTempView(f"{name}_vertices")
