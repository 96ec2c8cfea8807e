"""Tables written once to the folder that driver and executors share, and read back with their lineage cut."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame

from ..shipping import work_dir


def kept(df: DataFrame) -> DataFrame:
    """df as a Parquet table in the application's folder, see `freeseg.shipping.release`."""
    to = f"{work_dir(df.sparkSession)}/kept-{uuid.uuid4().hex}"
    df.write.parquet(to)
    return df.sparkSession.read.schema(df.schema).parquet(to)
