"""Loop support: reliable lineage cuts.

Every loop of this library keeps its state in DataFrames and sends only counters to
the driver.  A state is materialised in the shared checkpoint folder, so that the plan of round r
does not contain the plans of earlier rounds and a lost executor never loses the state.  ``written`` is
the form for loops: ``checkpoint`` keeps the constraints and estimated sizes of the plan it replaces, the
likely reason (measured by its effect only) why merge rounds took minutes with it.  Files carry
neither, only their true size.
"""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """Use the folder the cluster names in ``spark.checkpoint.dir``; a folder of its own only in a local session."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and not re.fullmatch(r"local(\[[^\]]*\])?", sc.master):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="linkcluster-ck-"))


def cut(df: DataFrame) -> DataFrame:
    """Materialise ``df`` in the shared checkpoint folder and drop its lineage."""
    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


#: Deletes the shuffle files of a statement at its end; else they stay until the driver happens to collect its garbage.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def written(df: DataFrame) -> DataFrame:
    """``df`` as a Parquet table in the shared checkpoint folder, read back with its schema.  Its shuffle files end with it."""
    spark = df.sparkSession
    ensure_checkpoint_dir(spark)
    path = f"{spark.sparkContext.getCheckpointDir()}/state-{uuid.uuid4().hex}"
    before = spark.conf.get(CLEANUP)
    spark.conf.set(CLEANUP, "true")
    try:
        df.write.option("compression", "zstd").parquet(path)
    finally:
        spark.conf.set(CLEANUP, before)
    return spark.read.schema(df.schema).parquet(path)


def release(*states: DataFrame) -> None:
    """Deletes written states that no plan reads any more; whatever is not one is left alone."""
    for df in states:
        spark = df.sparkSession
        jvm, top = spark._jvm, spark.sparkContext.getCheckpointDir()
        for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
            path = jvm.org.apache.hadoop.fs.Path(folder)
            if top and path.getName().startswith("state-") and path.getParent().getName() == top.rstrip("/").rsplit("/", 1)[-1]:
                path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
