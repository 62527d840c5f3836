"""What every operator needs of a session: the package on the workers, durable tables, a size limit for broadcasts."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame

from .ship import ship

#: Bytes up to which a small factor may be held by the driver and broadcast; larger ones stay distributed.
SMALL_BYTES = 256 << 20

__all__ = ["SMALL_BYTES", "durable", "shared_folder", "ship"]


def shared_folder(spark) -> str:
    """The folder for intermediate tables: the one that spark.checkpoint.dir names.

    Only a session without other machines may go without one; it gets a temporary folder.
    """
    sc = spark.sparkContext
    named = sc.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None)
    if named is None:
        if not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        named = tempfile.mkdtemp(prefix="frames-")
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(named)
    return named


_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def durable(df: DataFrame) -> DataFrame:
    """Written to the shared checkpoint folder and read from there; the shuffle files behind it, needed no more, are deleted once it is written.

    Second orthonormalisations need this: two evaluations of an ill-conditioned factor whose batches were cut
    differently differ far above machine precision, so every consumer must read the same copy.
    """
    spark = df.sparkSession
    shared_folder(spark)
    try:
        before = spark.conf.get(_CLEANUP)
    except Exception:  # a version of Spark without it
        return df.checkpoint(eager=True)
    spark.conf.set(_CLEANUP, "true")  # read when a plan is made
    try:
        return df.select("*").checkpoint(eager=True)
    finally:
        spark.conf.set(_CLEANUP, before)
