"""Schemas of the engine's tables and their check on entry."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType


def _of(ddl: str) -> StructType:
    return StructType.fromDDL(ddl)


NODE = _of("id LONG, feat ARRAY<DOUBLE>, label INT, split STRING")
EDGE = _of("src LONG, dst LONG, w DOUBLE")
PART = _of("id LONG, part INT")
REMOTE = _of("sp INT, dp INT, src LONG, dst LONG, w DOUBLE")
COVER = _of("sp INT, dp INT, side STRING, id LONG")
ROUTED = _of("sp INT, dp INT, src LONG, dst LONG, w DOUBLE, route STRING")
MESSAGE = _of("sp INT, dp INT, kind STRING, key LONG, blk INT, v ARRAY<DOUBLE>, n DOUBLE")
QROW = _of("id LONG, codes BINARY, bits INT, zp FLOAT, sc FLOAT")
COMM = _of("sp INT, dp INT, vectors LONG, elements LONG, bits LONG")
HISTORY = _of("epoch INT, split STRING, loss DOUBLE, accuracy DOUBLE, seconds DOUBLE")


def require_schema(df: DataFrame, schema: StructType) -> DataFrame:
    """The columns of ``schema`` in its order; raises where one is missing or of another type."""
    have = {f.name: f.dataType for f in df.schema}
    for f in schema:
        if f.name not in have:
            raise ValueError(f"column {f.name} is missing")
        if have[f.name].simpleString() != f.dataType.simpleString():
            raise TypeError(f"column {f.name} is {have[f.name].simpleString()}, not {f.dataType.simpleString()}")
    return df.select(*schema.fieldNames())


def width_of(df: DataFrame, column: str = "feat") -> int:
    """The one length of all vectors; raises where lengths differ."""
    r = df.agg(F.min(F.size(column)).alias("lo"), F.max(F.size(column)).alias("hi")).first()
    if r.lo is not None and r.lo != r.hi:
        raise ValueError(f"vectors of {r.lo} to {r.hi} elements")
    return r.hi or 0
