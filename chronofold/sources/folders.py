"""Where intermediate tables go."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import SparkSession


def scratch(spark: SparkSession) -> str:
    """A new folder under ``spark.checkpoint.dir``; where that is unset, a temporary one in local mode and the warehouse
    otherwise."""
    top = spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if not top:
        local = spark.sparkContext.master.startswith("local[")
        top = f"file://{tempfile.gettempdir()}" if local else spark.conf.get("spark.sql.warehouse.dir")
    return f"{top}/chronofold-{uuid.uuid4().hex}"
