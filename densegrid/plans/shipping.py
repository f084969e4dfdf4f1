"""Broadcasting Python objects whose classes the executors needn't have installed."""

from __future__ import annotations

import pickle
from collections.abc import Callable
from typing import Any

from pyspark import cloudpickle
from pyspark.sql import SparkSession


def ship(spark: SparkSession, value: Any) -> Callable[[], Any]:
    """Broadcasts ``value``; call the result once in a task to have it there."""
    sent = spark.sparkContext.broadcast(cloudpickle.dumps(value))
    return lambda: pickle.loads(sent.value)
