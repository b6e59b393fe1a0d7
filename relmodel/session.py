"""What the session gives: the folder that executors share, and workers that can import this package."""

from __future__ import annotations

import os
import tempfile
import uuid

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


def importable(spark) -> None:
    """Adds the package's folder to the workers' path; where executors do not see that folder, ship the
    package with --py-files. No setting of the session changes."""
    env = spark.sparkContext.environment
    paths = [p for p in env.get("PYTHONPATH", "").split(os.pathsep) if p]
    if ROOT not in paths:
        env["PYTHONPATH"] = os.pathsep.join([*paths, ROOT])


def shared_folder(spark) -> str:
    """The folder of ``spark.checkpoint.dir``; a local one only where there is one machine and none is named."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if base:
        return base.rstrip("/")
    master = spark.sparkContext.master
    if master != "local" and not master.startswith("local["):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return os.path.join(tempfile.gettempdir(), "relmodel-work")


def saved(df):
    """Cuts lineage: the rows written to the shared folder and read again."""
    path = f"{shared_folder(df.sparkSession)}/relmodel-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
