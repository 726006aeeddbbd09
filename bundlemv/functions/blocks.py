"""User-defined functions on blocks; each has a native twin in the operators."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType, LongType, StructField, StructType


def scatter_block(met: DataFrame, q: int) -> DataFrame:
    """(dst_block, src_block, srcs, vals of the source block) -> (dst_block, src_block, vals of the bundles)."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            base = b.column("src_block").to_numpy().astype(np.int64) * q
            vals = [np.asarray(v.values)[np.asarray(s.values) - o] for s, v, o in zip(b.column("srcs"), b.column("vals"), base)]
            yield pa.RecordBatch.from_arrays([b.column("dst_block"), b.column("src_block"), pa.array(vals, pa.list_(pa.float64()))], names=["dst_block", "src_block", "vals"])

    return met.mapInArrow(work, "dst_block int, src_block int, vals array<double>")


def gather_block(updates: DataFrame, lists: DataFrame, q: int, weighted: bool = False) -> DataFrame:
    """Sums of one destination block: running sums of flags pick the values, a weighted count adds them up."""

    def work(left: pa.Table, right: pa.Table) -> pa.Table:
        if not left.num_rows or not right.num_rows:
            return pa.table({"block": pa.array([], pa.int32()), "id": pa.array([], pa.int64()), "s": pa.array([], pa.float64())})
        vals = dict(zip(left.column("src_block").to_pylist(), left.column("vals").combine_chunks()))
        block = right.column("dst_block")[0].as_py()
        total, seen = np.zeros(q), np.zeros(q, bool)
        for i, src in enumerate(right.column("src_block").to_pylist()):
            if src in vals:
                local = np.asarray(right.column("ids")[i].values) - block * q
                at = np.cumsum(np.asarray(right.column("flags")[i].values).astype(np.int64)) - 1
                x = np.asarray(vals[src].values)[at]
                if weighted:
                    x = x * np.asarray(right.column("weights")[i].values)
                total += np.bincount(local, weights=x, minlength=q)
                seen[local] = True
        ids = np.nonzero(seen)[0]
        return pa.table({"block": pa.array(np.full(len(ids), block), pa.int32()), "id": pa.array(ids + block * q, pa.int64()), "s": pa.array(total[ids])})

    return updates.groupBy("dst_block").cogroup(lists.groupBy("dst_block")).applyInArrow(work, "block int, id long, s double")


@F.arrow_udf(ArrayType(LongType()))
def decode_ids(codes: pa.Array) -> pa.Array:
    """Arrays of flagged ids without their flags."""
    flat = codes.values.to_numpy(zero_copy_only=False) & np.int64((1 << 63) - 1)
    return pa.ListArray.from_arrays(codes.offsets, pa.array(flat))


@F.pandas_udf(DoubleType())
def l1_delta(a: pd.Series, b: pd.Series) -> float:
    """Sum of absolute differences, as an aggregate of one block; ``results.l1_delta`` is its native twin for whole tables."""
    return float((a.fillna(0) - b.fillna(0)).abs().sum())


@F.pandas_udf(DoubleType())
def gini(x: pd.Series) -> float:
    """Gini coefficient of nonnegative numbers, as an aggregate of one block; ``results.gini`` is its native twin for whole tables."""
    v = np.sort(x.to_numpy(dtype=float))
    n = len(v)
    return 0.0 if not n or v.sum() == 0 else float((2 * np.arange(1, n + 1) - n - 1) @ v / (n * v.sum()))


@F.udtf(returnType=StructType([StructField("dst", LongType()), StructField("v", DoubleType())]))
class ExpandBundle:
    """(value, ids, weights or null) -> a row (dst, contribution) per id."""

    def eval(self, value: float, ids: list, weights: list | None):
        for i, d in enumerate(ids):
            yield d, value * (weights[i] if weights else 1.0)


def register_functions(spark: SparkSession) -> None:
    """block_of, decode_ids and expand_bundle for SQL."""
    spark.sql("create or replace temporary function block_of(id bigint, shift int) returns bigint return shiftright(id, shift)")
    spark.udf.register("decode_ids", decode_ids)
    spark.udtf.register("expand_bundle", ExpandBundle)
