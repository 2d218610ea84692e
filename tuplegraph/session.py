"""Session settings that may change at run time, and the checkpoint folder."""

from __future__ import annotations

import os
import tempfile
from pathlib import Path

from pyspark.sql import SparkSession

#: Settings that plans rely on; all of them may be set on a running session.
SETTINGS = {"spark.sql.session.timeZone": "UTC", "spark.sql.adaptive.enabled": "true", "spark.sql.adaptive.skewJoin.enabled": "true"}


def prepare(spark: SparkSession) -> SparkSession:
    """Apply SETTINGS, make the package importable in workers, and name a checkpoint folder where none is set."""
    for key, value in SETTINGS.items():
        if spark.conf.get(key, None) != value:
            spark.conf.set(key, value)
    context, root = spark.sparkContext, str(Path(__file__).resolve().parents[1])
    known = context.environment.get("PYTHONPATH", "")
    if root not in known.split(os.pathsep):
        context.environment["PYTHONPATH"] = os.pathsep.join(x for x in (root, known) if x)
    if not context._jsc.sc().getCheckpointDir().isDefined():
        context.setCheckpointDir(context.getConf().get("spark.checkpoint.dir") or tempfile.mkdtemp(prefix="checkpoints-"))
    return spark


def shared_dir(spark: SparkSession) -> str:
    prepare(spark)
    return spark.sparkContext._jsc.sc().getCheckpointDir().get()
