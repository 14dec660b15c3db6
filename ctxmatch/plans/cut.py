"""Cutting the lineage of iterative plans."""

from __future__ import annotations

import atexit
import shutil
import tempfile

from pyspark.sql import DataFrame

_LOCAL: list[str] = []


def cut(df: DataFrame) -> DataFrame:
    """A reliable checkpoint in the folder of ``spark.checkpoint.dir``; a temporary one only where the setting is absent and all tasks run on this machine, as in tests."""
    context = df.sparkSession.sparkContext
    if context.getCheckpointDir() is None:
        folder = df.sparkSession.conf.get("spark.checkpoint.dir", None)
        if folder is None:
            if not context.master.startswith("local"):
                raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
            if not _LOCAL:
                _LOCAL.append(tempfile.mkdtemp(prefix="ctxmatch-"))
                atexit.register(shutil.rmtree, _LOCAL[0], ignore_errors=True)
            folder = "file://" + _LOCAL[0]
        context.setCheckpointDir(folder)
    return df.checkpoint(eager=True)
