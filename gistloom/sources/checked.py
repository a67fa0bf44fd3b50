"""Tables that fail at load when their schema is not the expected one, not in the middle of a job."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.types import StructType


def load_checked(spark: SparkSession, path: str, expected: StructType | str) -> DataFrame:
    """The expected columns of a table of files, in their order; further columns are not read.

    Raises ValueError that names every missing column and every other type.
    """
    wanted = StructType.fromDDL(expected) if isinstance(expected, str) else expected
    table = spark.read.parquet(path)
    found = {f.name: f.dataType for f in table.schema}
    faults = [f"{f.name} is missing" for f in wanted if f.name not in found]
    faults += [f"{f.name} is {found[f.name].simpleString()}, not {f.dataType.simpleString()}" for f in wanted if f.name in found and found[f.name] != f.dataType]
    if faults:
        raise ValueError(f"{path}: " + "; ".join(faults))
    return table.select(*wanted.names)
