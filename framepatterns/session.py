"""Session settings.  Only settings that may change at run time are touched on a session that is already started."""

from __future__ import annotations

import atexit
import shutil
import tempfile

from pyspark.sql import SparkSession

RUNTIME = {
    "spark.sql.adaptive.enabled": "true",
    "spark.sql.adaptive.skewJoin.enabled": "true",
    "spark.sql.execution.arrow.pyspark.enabled": "true",
    "spark.sql.session.timeZone": "UTC",
}


#: Settings of a session that is not yet running.
START = {"spark.speculation": "true", "spark.speculation.quantile": "0.9"}


def start(master: str = "local[*]", app: str = "framepatterns", **settings: str) -> SparkSession:
    """A new session, or the running one with its run-time settings adjusted.

    A new session also runs slow tasks twice: with small tasks dealt as workers become free (``oversplit``), this
    stands in for work stealing.
    """
    b = SparkSession.builder.master(master).appName(app)
    fixed = START if SparkSession.getActiveSession() is None else {}
    for k, v in (fixed | RUNTIME | settings).items():
        b = b.config(k, v)
    return b.getOrCreate()


def partitions_for(n_bytes: int, target: int = 128 << 20, least: int = 1) -> int:
    """Partitions so that each holds about ``target`` bytes: the count follows the data, not the cores."""
    return max(least, -(-n_bytes // target))


_FALLBACK: list[str] = []


def shared_root(spark: SparkSession) -> str:
    """The folder that all executors share, from spark.checkpoint.dir.

    Where the setting is missing, a temporary folder of this machine serves a local master; on a cluster other
    machines would not see it, so there it is an error.
    """
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if root:
        return root.rstrip("/")
    if spark.sparkContext.master.split("[")[0] != "local":
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    if not _FALLBACK:
        folder = tempfile.mkdtemp(prefix="framepatterns_")
        atexit.register(shutil.rmtree, folder, True)
        _FALLBACK.append("file://" + folder)
    return _FALLBACK[0]
