"""Session settings the library reads."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession


def checkpoint_folder(spark: SparkSession) -> str:
    """The shared folder for cut lineage: ``spark.checkpoint.dir`` where it is set, or the one the context has.  A
    session that runs in one process may do without (a temporary one is made); a cluster may not."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    context = spark.sparkContext
    if folder:
        if context.getCheckpointDir() is None:
            context.setCheckpointDir(folder)
        return folder
    if context.getCheckpointDir() is None:
        if not (context.master == "local" or context.master.startswith("local[")):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        context.setCheckpointDir(tempfile.mkdtemp(prefix="deltafold-checkpoint-"))
    return context.getCheckpointDir()


def cut(df: DataFrame) -> DataFrame:
    """The frame's rows written once to the shared folder and read from there: later uses agree, survive lost
    executors and do not repeat the work."""
    checkpoint_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def cut_and_free(df: DataFrame) -> DataFrame:
    """``cut`` for a frame that nothing else reads: the files of the shuffles that made it are deleted before this
    returns, not when the driver next collects garbage.  A frame that is read again after all runs its stages again."""
    out = cut(df)
    components = df.sparkSession.sparkContext._jsc.sc().shuffleDriverComponents()
    for n in _shuffles(df._jdf.queryExecution().executedPlan()):
        components.removeShuffle(n, True)
    return out


def _shuffles(plan) -> set[int]:
    """Ids of the shuffles of a plan that ran."""
    kind = plan.getClass().getSimpleName()
    if kind == "AdaptiveSparkPlanExec":
        return set(plan.context().shuffleIds().keySet().toArray())
    below = plan.children()
    found = [_shuffles(below.apply(i)) for i in range(below.length())]
    return set().union(*found, [plan.shuffleId()] if kind == "ShuffleExchangeExec" else [])
