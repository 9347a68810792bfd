"""Objects for Python workers that need no copy of this package on their path."""

from __future__ import annotations

import gc
from typing import Any

from pyspark import Broadcast, cloudpickle
from pyspark.sql import SparkSession


def share(spark: SparkSession, value: Any) -> Broadcast:
    """Broadcast ``value`` together with the classes it is made of."""
    return spark.sparkContext.broadcast(cloudpickle.dumps(value))


def held(shared: Broadcast) -> Any:
    """The value behind ``share``; a worker unpacks it once and keeps it while it keeps the broadcast.

    Values of stages before, which cycles through shipped classes may hold in a worker that is used again, go first."""
    value = getattr(shared, "_unpacked", None)
    if value is None:
        gc.collect()
        value = shared._unpacked = cloudpickle.loads(shared.value)
    return value
