"""Sessions: settings for one's own, and what a session that somebody else started needs."""

from __future__ import annotations

import os
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

ROOT = Path(__file__).resolve().parent.parent
_SHIPPED: set[str] = set()
_OWN: dict[str, str] = {}


def build_session(name: str = "sightline", master: str | None = None, **settings: str) -> SparkSession:
    """A session with UTC, adaptive execution, Arrow and the RocksDB state store."""
    conf = {
        "spark.sql.session.timeZone": "UTC",
        "spark.sql.adaptive.enabled": "true",
        "spark.sql.execution.arrow.pyspark.enabled": "true",
        "spark.sql.streaming.stateStore.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider",
        "spark.ui.enabled": "false",
    } | {k.replace("__", "."): v for k, v in settings.items()}
    builder = SparkSession.builder.appName(name)
    if master:
        builder = builder.master(master)
    for k, v in conf.items():
        builder = builder.config(k, v)
    return builder.getOrCreate()


def shared_dir(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``, which all executors must share; a temporary one where it is unset and Spark is one local process."""
    named = spark.conf.get("spark.checkpoint.dir", "") or spark.sparkContext.getConf().get("spark.checkpoint.dir", "")
    if named:
        return named.rstrip("/")
    if spark.sparkContext.master.partition("[")[0] != "local":
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if "dir" not in _OWN:
        _OWN["dir"] = tempfile.mkdtemp(prefix="sightline-shared-")
    return _OWN["dir"]


def ship_package(spark: SparkSession) -> None:
    """Send this package to the Python workers, unless their path has it already or it was sent before."""
    app = spark.sparkContext.applicationId
    known = {os.path.realpath(p) for p in os.environ.get("PYTHONPATH", "").split(os.pathsep) if p}
    if app in _SHIPPED or str(ROOT) in known:
        return
    target = Path(tempfile.mkdtemp(prefix="sightline-")) / "sightline_package.zip"
    with zipfile.ZipFile(target, "w") as z:
        for f in sorted((ROOT / "sightline").rglob("*.py")):
            z.write(f, f.relative_to(ROOT))
    spark.sparkContext.addPyFile(str(target))
    _SHIPPED.add(app)
