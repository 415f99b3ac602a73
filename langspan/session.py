"""Durable lineage cuts in the folder that the running session names."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame

#: Shuffle files of a query go when its action ends, not when the driver happens to collect its garbage.
CLEANED = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def durable(df: DataFrame) -> DataFrame:
    """A reliable checkpoint in the folder of ``spark.checkpoint.dir``. Where that is unset a local master gets a folder of
    its own (tests); a cluster, whose machines could not share it, an error. What was shuffled for it goes at once: a driver with
    memory to spare may plan many small queries before it collects its garbage, while their files pile up."""
    spark = df.sparkSession
    context = spark.sparkContext
    if context._jsc.sc().getCheckpointDir().isEmpty():
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if not folder and not context.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        context.setCheckpointDir(folder or tempfile.mkdtemp(prefix="checkpoints-"))
    before = spark.conf.get(CLEANED, None)
    spark.conf.set(CLEANED, "true")
    try:
        return df.select("*").checkpoint()  # a query of its own: no other shares its shuffles
    finally:
        spark.conf.set(CLEANED, before) if before is not None else spark.conf.unset(CLEANED)
