"""Session settings of round loops, and the shared folder."""

from __future__ import annotations

import contextlib
import tempfile
import uuid

from py4j.protocol import Py4JJavaError
from pyspark.sql import DataFrame, SparkSession


@contextlib.contextmanager
def loop_conf(spark: SparkSession, partitions: int, broadcast: bool = False):
    """Settings under which partitioning survives from round to round.

    Adaptive execution would hide the partitioning of a kept state, and so add an
    exchange a round; all exchanges of a loop must have the same partition count.
    """
    own = {
        "spark.sql.adaptive.enabled": "false",
        "spark.sql.shuffle.partitions": str(partitions),
        "spark.sql.autoBroadcastJoinThreshold": spark.conf.get("spark.sql.autoBroadcastJoinThreshold") if broadcast else "-1",
        "spark.sql.optimizer.canChangeCachedPlanOutputPartitioning": "false",
    }
    before = {k: spark.conf.get(k, None) for k in own}
    try:
        for k, v in own.items():
            spark.conf.set(k, v)
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def shared_dir(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir, which all executors see; a temporary one only where none is set and all run in one process."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        if held.isEmpty():
            if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
                raise RuntimeError("spark.checkpoint.dir must name a folder that all executors see")
            spark.sparkContext.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="netprop-"))
            held = spark.sparkContext._jsc.sc().getCheckpointDir()
        found = held.get()
    return found.rstrip("/")


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex[:12]}"


def remove(spark: SparkSession, path: str) -> None:
    """Delete a path of any Hadoop file system."""
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


def stored(df: DataFrame, name: str) -> DataFrame:
    path = fresh_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def size_of(spark: SparkSession, path: str) -> int:
    """Bytes under a path of any Hadoop file system; 0 where there is none."""
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    files = target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    return files.getContentSummary(target).getLength() if files.exists(target) else 0


def checkpoint_path(df: DataFrame) -> str | None:
    """Where a checkpointed frame's rows lie."""
    held = df._jdf.queryExecution().analyzed().rdd().getCheckpointFile()
    return held.get() if held.isDefined() else None


def cut(df: DataFrame) -> DataFrame:
    """A persisted frame as the leaf of a new plan, with its partitioning; nothing is written.

    Else each round's plan would hold those of all rounds before, twice. The lineage
    stays behind it, so lost executors cost a recomputation and no more.
    """
    jvm, made = df.sparkSession.sparkContext._jvm, df.select("*")._jdf  # planned anew: a plan made before the frame was persisted would compute it again
    leaves = getattr(getattr(jvm.org.apache.spark.sql.execution, "LogicalRDD$"), "MODULE$")
    leaf = leaves.fromDataset(made.queryExecution().toRdd(), made, False)
    return DataFrame(jvm.org.apache.spark.sql.classic.Dataset.ofRows(df.sparkSession._jsparkSession, leaf), df.sparkSession)


@contextlib.contextmanager
def measured(spark: SparkSession):
    """A dict that after the block holds what its jobs sent through exchanges and wrote to tables, as rows and bytes.

    Taken from the stages' own counters, so after the combiner.
    """
    sc, group, seen = spark.sparkContext, f"netprop-{uuid.uuid4().hex}", {}
    before = sc.getLocalProperty("spark.jobGroup.id")
    sc.setLocalProperty("spark.jobGroup.id", group)
    try:
        yield seen
    finally:
        sc.setLocalProperty("spark.jobGroup.id", before)
    sc._jsc.sc().listenerBus().waitUntilEmpty()
    store, tracker = sc._jsc.sc().statusStore(), sc.statusTracker()
    stages = {s for job in tracker.getJobIdsForGroup(group) if (info := tracker.getJobInfo(job)) for s in info.stageIds}
    data = []
    for s in stages:
        try:
            data.append(store.lastStageAttempt(s))
        except Py4JJavaError:  # a skipped stage, of which a long session keeps nothing
            pass
    seen |= {"shuffle_rows": sum(d.shuffleWriteRecords() for d in data), "shuffle_bytes": sum(d.shuffleWriteBytes() for d in data), "written_rows": sum(d.outputRecords() for d in data), "written_bytes": sum(d.outputBytes() for d in data)}
