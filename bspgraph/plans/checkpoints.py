"""Lineage cuts that keep the layout of a loop's tables."""

from __future__ import annotations

import contextlib
import gc
import re
import tempfile

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession

#: Settings of the superstep loop.  Adaptive execution would forget the layout
#: of a checkpointed table; joins on (pid, id) may rely on pid alone; broadcasts
#: are decided by the engine from counted sizes; lists of identifiers, which the
#: engine bounds, are pushed into scans whole; buckets are read as buckets; queues
#: are gathered from sorted mail, as hashing them would sort it all the same, twice.
LOOP = {
    "spark.sql.adaptive.enabled": "false",
    "spark.sql.requireAllClusterKeysForCoPartition": "false",
    "spark.sql.autoBroadcastJoinThreshold": "-1",
    "spark.sql.parquet.pushdown.inFilterThreshold": "1024",
    "spark.sql.sources.bucketing.autoBucketedScan.enabled": "false",
    "spark.sql.execution.useObjectHashAggregateExec": "false",
}


@contextlib.contextmanager
def loop_settings(spark: SparkSession):
    """The loop's settings, put back at the end, also after an error."""
    before = {k: spark.conf.get(k, None) for k in LOOP}
    try:
        for k, v in LOOP.items():
            spark.conf.set(k, v)
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def shared_folder(spark: SparkSession) -> str:
    """The session's checkpoint folder.  One is made only where none is named and
    the session runs in one process; on a cluster a local folder would be lost."""
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        if named is None and not re.fullmatch(r"local(\[[^\]]*\])?", context.master):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        context.setCheckpointDir(named or tempfile.mkdtemp(prefix="checkpoints-"))
    return context.getCheckpointDir()


def cut(df: DataFrame) -> DataFrame:
    """Write ``df`` to the shared folder; partitioning and order are kept.  The files
    stay until they are dropped or no frame that reads them is left."""
    shared_folder(df.sparkSession)
    return _unsized(df.checkpoint(eager=True))


def _unsized(df: DataFrame) -> DataFrame:
    """A checkpointed frame without an estimate of its size.  Spark hands on the
    estimate of the plan that made it, for a join the product of both sides; from
    cut to cut of a loop that number doubles its digits, until planning ends in it."""
    spark, leaf = df.sparkSession, df._jdf.queryExecution().analyzed()
    jvm, none = spark.sparkContext._jvm, spark.sparkContext._jvm.scala.Option.empty()
    cleaner = spark.sparkContext._jsc.sc().cleaner()
    if cleaner.isDefined():
        kept = leaf.rdd().checkpointData().get()
        cleaner.get().registerRDDCheckpointDataForCleanup(kept.checkpointRDD().get(), leaf.rdd().id())
    sql = jvm.org.apache.spark.sql
    plan = sql.execution.LogicalRDD(leaf.output(), leaf.rdd(), leaf.outputPartitioning(), leaf.outputOrdering(), False, none, spark._jsparkSession, none, none)
    return DataFrame(sql.classic.Dataset.ofRows(spark._jsparkSession, plan), spark)


def pack(df: DataFrame) -> tuple[DataFrame, dict]:
    """Write ``df`` to the shared folder as columns, and what it observed by name.
    Partitioning and order are kept as with ``cut``, whose files hold one Java object
    a row: a loop that reads its tables in every step spends most of its time on those.
    The job is not an SQL execution, whose plan and metrics the driver would keep."""
    shared_folder(df.sparkSession)
    spark, done = df.sparkSession, df._jdf.queryExecution()
    jvm, context, none = spark.sparkContext._jvm, spark.sparkContext._jsc.sc(), spark.sparkContext._jvm.scala.Option.empty()
    sql, plan = jvm.org.apache.spark.sql, done.executedPlan()
    columns, conf = plan.output(), spark._jsparkSession.sessionState().conf()
    form = sql.execution.columnar.DefaultCachedBatchSerializer()
    batches = form.convertInternalRowToCachedBatch(done.toRdd(), columns, spark.sparkContext._getJavaStorageLevel(StorageLevel.DISK_ONLY), conf)
    batches.checkpoint()
    batches.doCheckpoint()
    if context.cleaner().isDefined():
        context.cleaner().get().registerRDDCheckpointDataForCleanup(batches.checkpointData().get().checkpointRDD().get(), batches.id())
    seen, named = {}, done.observedMetrics().valuesIterator()
    while named.hasNext():
        row = named.next()
        seen |= dict(zip(row.schema().fieldNames(), (row.get(i) for i in range(row.size()))))
    dealt = plan.outputPartitioning()
    while dealt.getClass().getSimpleName() == "PartitioningCollection":
        dealt = dealt.partitionings().head()
    rows = form.convertCachedBatchToInternalRow(batches, columns, columns, conf)
    leaf = sql.execution.LogicalRDD(columns, rows, dealt, plan.outputOrdering(), False, none, spark._jsparkSession, none, none)
    return DataFrame(sql.classic.Dataset.ofRows(spark._jsparkSession, leaf), spark), seen


def release(spark: SparkSession) -> None:
    """Have Spark's cleaner delete the files of cut frames that nothing refers to."""
    gc.collect()
    spark.sparkContext._jvm.java.lang.System.gc()


def drop(*frames: DataFrame | None) -> None:
    """Delete the files of frames that ``cut`` or ``pack`` returned and nobody reads again."""
    for df in frames:
        if df is None:
            continue
        leaves = df._jdf.queryExecution().analyzed().collectLeaves()
        for i in range(leaves.size()):
            leaf = leaves.apply(i)
            if leaf.getClass().getSimpleName() == "LogicalRDD":
                rdd = leaf.rdd()
                if not rdd.getCheckpointFile().isDefined() and rdd.dependencies().nonEmpty():  # columns lie below the rows
                    rdd = rdd.dependencies().head().rdd()
                remove(df.sparkSession, rdd.getCheckpointFile())


def remove(spark: SparkSession, path) -> None:
    """Delete a folder (a string or a JVM option of one) of any file system."""
    if not isinstance(path, str):
        if not path.isDefined():
            return
        path = path.get()
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


@contextlib.contextmanager
def held(df: DataFrame, level: StorageLevel):
    """``df`` in the storage that was chosen, for the time of a run: in memory
    it is cached, out of core it is read from the shared folder each time."""
    if level == StorageLevel.DISK_ONLY:
        yield df
        return
    kept = df.persist(level)
    try:
        yield kept
    finally:
        kept.unpersist()
