"""Runtime settings that the profile plans want. Only settings that a running session may change."""

from __future__ import annotations

import contextlib

from pyspark.sql import SparkSession

#: A grouped sketch aggregation falls back to sorting beyond this many keys of a task; profiles have up to MAX_PATHS keys.
MAX_PATHS = 20_000
SETTINGS = {"spark.sql.objectHashAggregate.sortBased.fallbackThreshold": str(2 * MAX_PATHS), "spark.sql.session.timeZone": "UTC"}


def tune(spark: SparkSession) -> None:
    for k, v in SETTINGS.items():
        with contextlib.suppress(Exception):  # a session that forbids it still gives right results, by sorting
            spark.conf.set(k, v)
