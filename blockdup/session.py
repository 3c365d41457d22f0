"""Session helper for tests and the benchmark; library code takes the session it is given."""

from __future__ import annotations

import time

from pyspark.sql import SparkSession


def local_session(cores: int = 8, partitions: int = 8, memory: str = "8g") -> SparkSession:
    """A local session, tried twice: the Java gateway now and then fails at its first start."""
    for attempt in (1, 2):
        try:
            return (
                SparkSession.builder.master(f"local[{cores}]").appName("blockdup")
                .config("spark.driver.memory", memory)
                .config("spark.sql.shuffle.partitions", str(partitions))
                .config("spark.sql.session.timeZone", "UTC")
                .config("spark.ui.enabled", "false")
                .config("spark.ui.showConsoleProgress", "false")
                .getOrCreate()
            )
        except Exception as why:
            if attempt == 2:
                raise
            print(f"the session did not start ({why}); trying once more")
            time.sleep(3)
    raise AssertionError
