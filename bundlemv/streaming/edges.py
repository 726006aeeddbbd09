"""Edges from a stream of events, and ranks that follow them."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType, TimestampType

from bundlemv.graph import Graph
from bundlemv.operators.blocks import blocked
from bundlemv.operators.layout import Packed, packed_pairs
from bundlemv.operators.rank import Prepared, run, vertex_table
from bundlemv.operators.steps import allow_placement, bundled_on

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def read_events(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """The events under ``path`` as a stream of files."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def window_counts(events: DataFrame, width: str = "1 day", slide: str | None = None, late: str = "1 day") -> DataFrame:
    """start, event_type, events, total: tumbling windows, or sliding ones; rows later than the watermark are dropped."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    own = events.withWatermark("ts", late).groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("events"), F.sum("value").alias("total"))
    return own.select(F.col("w.start").alias("start"), "event_type", "events", "total")


def session_counts(events: DataFrame, gap: str = "6 hours", late: str = "1 day") -> DataFrame:
    """user_id, start, events: sessions of a user that end after a gap."""
    own = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("events"))
    return own.select("user_id", F.col("w.start").alias("start"), "events")


def without_repeats(events: DataFrame, late: str = "1 day") -> DataFrame:
    """Events once per id within the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


_OUT = StructType([StructField("user_id", LongType()), StructField("src_type", LongType()), StructField("dst_type", LongType()), StructField("ts", TimestampType())])
_STATE = StructType([StructField("last", LongType())])


def type_transitions(events: DataFrame) -> DataFrame:
    """user_id, src_type, dst_type, ts: each event of a user with the type of the user's event before, kept as state.

    Types are numbered by hash. Within a batch events go by time; a batch that comes late
    follows what was seen.
    """
    coded = events.select("user_id", "ts", "event_id", F.pmod(F.xxhash64("event_type"), F.lit(1 << 31)).alias("t"))

    def step(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        last = state.get[0] if state.exists else None
        before = [last, *rows.t.tolist()[:-1]]
        state.update((int(rows.t.iloc[-1]),))
        keep = [b is not None for b in before]
        yield pd.DataFrame({"user_id": key[0], "src_type": [b for b in before if b is not None], "dst_type": rows.t[keep].tolist(), "ts": rows.ts[keep].tolist()})

    return coded.groupBy("user_id").applyInPandasWithState(step, _OUT, _STATE, "append", "NoTimeout")


def late_rows(query) -> int:
    """Rows that a running or ended stream has dropped behind its watermarks, over the progress it still knows."""
    return sum(int(op["numRowsDroppedByWatermark"]) for p in query.recentProgress for op in p["stateOperators"])


class LiveRank:
    """Ranks that follow appended edges.

    A batch writes its new edges and, of the layout, the rows of the block pairs that they
    touch; nothing that stands is rewritten, and the newest row of a pair counts. The ranks run
    on that layout and start from the last ones. Hub blocks are not cut into chunks here.
    """

    def __init__(self, spark: SparkSession, n: int, q: int, path: str, iters: int = 5):
        self.spark, self.n, self.q, self.path, self.iters = spark, n, q, path, iters
        self.version, self.ranks = 0, None

    def edges(self) -> DataFrame:
        return self.spark.read.parquet(f"{self.path}/edges").select("src", "dst")

    def lists(self) -> DataFrame:
        """dst_block, chunk, src_block, ids, pos, srcs: the newest row of each block pair."""
        rows = self.spark.read.parquet(f"{self.path}/pairs")
        newest = rows.groupBy("dst_block", "src_block").agg(F.max("version").alias("version"))
        return rows.join(newest, ["dst_block", "src_block", "version"], "left_semi").drop("version")

    def layout(self) -> DataFrame:
        return self.lists().select("src_block", "dst_block", "chunk", "srcs")

    def append(self, new: DataFrame, _batch: int = 0) -> None:
        """For foreachBatch: add distinct edges (src, dst), build touched pairs anew, refresh the ranks."""
        fresh = new.select("src", "dst").distinct()
        if self.version:
            fresh = fresh.join(self.edges(), ["src", "dst"], "left_anti")
        self.version += 1
        fresh.write.parquet(f"{self.path}/edges/version={self.version}")
        fresh = self.spark.read.schema("src long, dst long").parquet(f"{self.path}/edges/version={self.version}")
        touched = blocked(Graph(fresh, self.n), self.q).select("src_block", "dst_block").distinct()
        inside = blocked(Graph(self.edges(), self.n), self.q).join(touched, ["src_block", "dst_block"], "left_semi").select("src", "dst")
        built = packed_pairs(Graph(inside, self.n), self.q, chunk_edges=1 << 62)
        built.lists.write.parquet(f"{self.path}/pairs/version={self.version}")
        for df in (built.lists, built.layout):
            df.unpersist()
        allow_placement(self.spark)
        p = Packed(self.layout(), self.lists().drop("srcs"), self.q, False, False).placed()
        vertices = vertex_table(Graph(self.edges(), self.n), self.q).sortWithinPartitions("block", "id").persist()
        ranks = run(None, prepared=Prepared(self.n, self.q, vertices, bundled_on(p)), iters=self.iters, start=self.ranks)
        for df in (p.layout, p.lists, vertices):  # the next batch reads the same folders, which hold more then
            df.unpersist()
        ranks.write.parquet(f"{self.path}/ranks/version={self.version}")
        self.ranks = self.spark.read.parquet(f"{self.path}/ranks/version={self.version}")
