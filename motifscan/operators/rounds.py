"""One round: joins at a key use the partitioning that the rows were shipped in. And what a run really shipped."""

from __future__ import annotations

import time
import uuid

from pyspark.sql import DataFrame, SparkSession

#: Spark partitions both sides of a join by all of its columns unless this is off; then rows that are together by the key stay where they are.
_ALL_COLUMNS = "spark.sql.requireAllClusterKeysForCoPartition"


def one_round(df: DataFrame) -> DataFrame:
    """The same rows, planned in a copy of the session in which joins on a key and more columns don't ship rows again.

    The setting holds for this DataFrame and what is made from it; the given session keeps its own.
    """
    if not hasattr(df, "_jdf"):  # a remote session plans as it likes
        return df
    spark = df.sparkSession
    own = spark._jsparkSession.cloneSession()
    own.conf().set(_ALL_COLUMNS, "false")
    plan = df._jdf.queryExecution().analyzed()
    return DataFrame(spark._jvm.org.apache.spark.sql.classic.Dataset.ofRows(own, plan), SparkSession(spark.sparkContext, own))


def guarded_cross(left: DataFrame, right: DataFrame, most: int = 1 << 32) -> DataFrame:
    """The product of two sides whose sizes are counted first: more than `most` rows stop the job rather than run away."""
    n = left.limit(most + 1).count()
    if n * right.limit(most // max(1, n) + 1).count() > most:
        raise ValueError(f"a product of more than {most} rows")
    return left.crossJoin(right)


def exchanges(df: DataFrame) -> list[str]:
    """Runs df; what each shuffle of the plan, as it ended up, was dealt by. Those that only read another's rows again aren't among them."""
    df.collect()
    found: list[str] = []

    def walk(plan: object) -> None:
        name = plan.nodeName()
        if name == "AdaptiveSparkPlan":
            walk(plan.executedPlan())
        elif "QueryStage" in name:
            walk(plan.plan())
        elif name == "ReusedExchange":
            return
        else:
            if name == "Exchange":
                found.append(plan.outputPartitioning().toString())
            children = plan.children()
            for i in range(children.size()):
                walk(children.apply(i))

    walk(df._jdf.queryExecution().executedPlan())
    return found


def run_figures(df: DataFrame) -> dict[str, float]:
    """Runs df without keeping its rows: rows and MB that its stages shuffled, MB spilled, seconds of its tasks, and seconds by the clock."""
    context = df.sparkSession.sparkContext
    group = uuid.uuid4().hex
    context.setJobGroup(group, "measured run")
    began = time.time()
    try:
        df.write.format("noop").mode("overwrite").save()
    finally:
        context.setLocalProperty("spark.jobGroup.id", None)
    seconds, store, tracker = time.time() - began, context._jsc.sc().statusStore(), context.statusTracker()
    stages = {s for j in tracker.getJobIdsForGroup(group) if (job := tracker.getJobInfo(j)) for s in job.stageIds}
    out = {"rows": 0.0, "mb": 0.0, "spill_mb": 0.0, "task_s": 0.0}
    for s in stages:
        data = store.lastStageAttempt(s)
        out["rows"] += data.shuffleWriteRecords()
        out["mb"] += data.shuffleWriteBytes() / 1e6
        out["spill_mb"] += data.diskBytesSpilled() / 1e6
        out["task_s"] += data.executorRunTime() / 1e3
    return out | {"seconds": seconds}
