"""Tables that are written once and read often."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


#: Folders made for local applications that name none.
_OWN: dict[str, str] = {}


def shared(spark: SparkSession, what: str) -> str:
    """A new path in the folder that all executors share, ``spark.checkpoint.dir``. Where it is unset a local master gets a
    fresh folder (tests); a cluster raises an error."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        app = spark.sparkContext.applicationId
        if app not in _OWN:
            _OWN[app] = "file://" + tempfile.mkdtemp(prefix="stage-")
        root = _OWN[app]
    return f"{root.rstrip('/')}/{what}-{uuid.uuid4().hex}"


def settle(df: DataFrame, what: str = "stage") -> DataFrame:
    """Writes df to the shared folder and reads it back, so that many passes read one table and none depends on an executor
    that may be lost."""
    path = shared(df.sparkSession, what)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
