from __future__ import annotations

from pyspark.sql import SparkSession


def get(app: str = "tgengine", conf: dict[str, str] | None = None) -> SparkSession:
    """A session with the settings that the engine expects; a started one is used as it is."""
    builder = SparkSession.builder.appName(app).config("spark.sql.adaptive.enabled", "true").config("spark.sql.session.timeZone", "UTC")
    for k, v in (conf or {}).items():
        builder = builder.config(k, v)
    return builder.getOrCreate()
