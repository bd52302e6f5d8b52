"""What a run takes: wall time, rows read and bytes shuffled, from Spark's own stage records."""

from __future__ import annotations

import contextlib
import time
from dataclasses import dataclass

from pyspark.sql import SparkSession


@dataclass
class Taken:
    seconds: float = 0.0
    rows_read: int = 0
    shuffle_bytes: int = 0
    stages: int = 0


def _stages(spark: SparkSession) -> dict[int, tuple[int, int]]:
    store = spark.sparkContext._jsc.sc().statusStore()
    gateway = spark.sparkContext._gateway
    listed = store.stageList(None, False, False, gateway.new_array(gateway.jvm.double, 0), None)
    return {s.stageId(): (s.inputRecords(), s.shuffleWriteBytes()) for s in (listed.apply(k) for k in range(listed.size()))}


@contextlib.contextmanager
def taken(spark: SparkSession):
    """Within the block, fill a Taken with what the session's stages do (those that Spark still remembers)."""
    out, before, began = Taken(), _stages(spark), time.time()
    try:
        yield out
    finally:
        out.seconds = round(time.time() - began, 3)
        new = [v for k, v in _stages(spark).items() if k not in before]
        out.rows_read, out.shuffle_bytes, out.stages = sum(r for r, _ in new), sum(b for _, b in new), len(new)
