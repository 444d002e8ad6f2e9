"""The fixed schemas of edges, nodes, slices and labels."""

from pyspark.sql import types as T


def _schema(**fields: T.DataType) -> T.StructType:
    return T.StructType([T.StructField(k, v) for k, v in fields.items()])


EDGES = _schema(slice=T.IntegerType(), src=T.LongType(), dst=T.LongType(), weight=T.DoubleType())
TEMPORAL_NODES = _schema(slice=T.IntegerType(), node=T.LongType())
SUPRA_EDGES = _schema(a=T.LongType(), b=T.LongType(), weight=T.DoubleType(), kind=T.StringType())
COUPLING = _schema(slice_a=T.IntegerType(), slice_b=T.IntegerType(), omega=T.DoubleType())
LABELS = _schema(slice=T.IntegerType(), node=T.LongType(), community=T.LongType())
EVENTS = _schema(event_id=T.LongType(), ts=T.TimestampNTZType(), user_id=T.LongType(), event_type=T.StringType(), props=T.StringType())
EVENT_ROWS = T.StructType([*EVENTS.fields[:2], *EVENTS.fields[2:4], T.StructField("value", T.DoubleType()), EVENTS.fields[4]])
