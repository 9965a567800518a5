"""Column layouts of the engine's tables."""

from pyspark.sql import types as T

_long = lambda name, null=True: T.StructField(name, T.LongType(), null)
VERTICES = T.StructType([_long("id", False)])
EDGES = T.StructType([_long("src", False), _long("dst", False)])
LABELS = T.StructType([_long("id"), _long("label")])
VOCABULARY = T.StructType([_long("id"), T.StructField("kind", T.StringType()), T.StructField("key", T.StringType())])
COMPONENTS = T.StructType([_long("component"), _long("size"), _long("min_id"), _long("max_id")])
TRACE = T.StructType([T.StructField("graph", T.StringType()), T.StructField("method", T.StringType()), T.StructField("iteration", T.IntegerType()), T.StructField("order", T.IntegerType()), _long("changed"), _long("violations"), _long("edge_rows"), T.StructField("seconds", T.DoubleType())])
INTEGERS = (T.ByteType, T.ShortType, T.IntegerType, T.LongType)
