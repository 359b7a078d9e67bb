"""Seeded vertex order: no global sort, any two vertices compare by (priority, id)."""

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Priorities are below this number.
SPAN = 1 << 60


def priority(v: Column, seed: Column | int = 42) -> Column:
    """The first 15 hexadecimal digits of md5('seed:id') as a long."""
    seed = F.lit(seed) if isinstance(seed, int) else seed
    text = F.concat(seed.cast("string"), F.lit(":"), v.cast("string"))
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 15), 16, 10).cast("long")


def priorities(vertices: DataFrame, seed: int = 42) -> DataFrame:
    return vertices.select("v", priority(F.col("v"), seed).alias("p"))
