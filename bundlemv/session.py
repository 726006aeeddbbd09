"""What the engine needs from the running session: a shared folder and importable workers."""

from __future__ import annotations

import os
import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

_LOCAL_FALLBACK = "/tmp/checkpoints"


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``.

    Only a local-mode session without that setting gets a folder of its own; on a
    cluster a missing setting is an error, because a machine-local folder would
    lose data.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        sc = spark.sparkContext
        if not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = f"file://{_LOCAL_FALLBACK}/{sc.applicationId}"
        if sc._jsc.sc().getCheckpointDir().isEmpty():
            sc.setCheckpointDir(base)
    return base.rstrip("/")


@contextmanager
def setting(spark: SparkSession, name: str, value: str) -> Iterator[None]:
    """A setting of the session that holds inside."""
    old = spark.conf.get(name)
    spark.conf.set(name, value)
    try:
        yield
    finally:
        spark.conf.set(name, old)


def scratch_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def drop_at_exit(spark: SparkSession, path: str) -> None:
    """Let what stands at ``path`` go when the driver's JVM ends."""
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(target)


def _plain(path: str) -> str:
    """The name that tells a scratch table from all others."""
    return path.rsplit("/", 1)[-1]


def drop_now(spark: SparkSession, path: str) -> None:
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


def read_by(df: DataFrame) -> list[str] | None:
    """Folders that the plan of ``df`` reads; None if it holds a cache, behind which anything may be read."""
    leaves, out = df._jdf.queryExecution().analyzed().collectLeaves(), []
    for i in range(leaves.size()):
        kind = leaves.apply(i).getClass().getSimpleName()
        if kind == "InMemoryRelation":
            return None
        if kind == "LogicalRelation" and leaves.apply(i).relation().getClass().getSimpleName() == "HadoopFsRelation":
            roots = leaves.apply(i).relation().location().rootPaths()
            out += [roots.apply(j).toString() for j in range(roots.size())]
    return out


class Scratch:
    """Scratch tables of a job of several steps, whose results are usually written before the next step begins.

    ``with scratch.step(docs)``: tables made inside are held until a later step begins whose
    input does not read them, and go then.
    """

    open: Scratch | None = None

    def __init__(self):
        self.paths: list[str] = []

    @contextmanager
    def step(self, docs: DataFrame) -> Iterator[None]:
        read = read_by(docs) if self.paths else []
        keep = [p for p in self.paths if read is None or any(_plain(p) in x for x in read)]
        for path in set(self.paths) - set(keep):
            drop_now(docs.sparkSession, path)
        self.paths, outer, Scratch.open = keep, Scratch.open, self
        try:
            yield
        finally:
            Scratch.open = outer


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and read it back.

    Cuts the lineage with a copy that outlives any executor. The copy goes with the session, or
    earlier with ``Scratch`` or ``discard``.
    """
    spark = df.sparkSession
    path = scratch_path(spark, name)
    df.write.parquet(path)
    drop_at_exit(spark, path)
    if Scratch.open is not None:
        Scratch.open.paths.append(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.scratch = path
    return out


def discard(df: DataFrame) -> None:
    """Drop the copy that ``materialise`` made, when nothing reads it any more."""
    drop_now(df.sparkSession, df.scratch)


#: Rows and bytes that one Arrow batch holds; a worker has a few batches in memory at once.
BATCH_ROWS, BATCH_BYTES = 1000, 8 << 20


def prepare_workers(spark: SparkSession) -> None:
    """Let Python workers import this package from the same place as the driver, and bound their batches."""
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH_ROWS))
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))
    root = str(Path(__file__).resolve().parent.parent)
    env = spark.sparkContext.environment
    have = env.get("PYTHONPATH", os.environ.get("PYTHONPATH", ""))
    if root not in have.split(os.pathsep):
        env["PYTHONPATH"] = os.pathsep.join(x for x in (have, root) if x)
