"""Declared schemas of the engine's tables."""

from pyspark.sql import types as T

_L, _S, _I, _D = T.LongType(), T.StringType(), T.IntegerType(), T.DoubleType()
PATH_STEP = T.StructType([T.StructField("node_id", _S), T.StructField("level", _I), T.StructField("w", _L), T.StructField("depth", _L)])
ONTOLOGY = T.StructType([
    T.StructField("node_id", _S), T.StructField("parent_id", _S), T.StructField("level", _I), T.StructField("w", _L),
    T.StructField("label", _S), T.StructField("depth", _L), T.StructField("path", T.ArrayType(PATH_STEP)),
])
CLOSURE = T.StructType([T.StructField("node_id", _S), T.StructField("anc_id", _S), T.StructField("anc_level", _I), T.StructField("dist", _L)])
OBJECTS = T.StructType([T.StructField("obj_id", _L), T.StructField("term_id", _S)])
PAIRS = T.StructType([T.StructField("a", _L), T.StructField("b", _L)])
TOPK = T.StructType([T.StructField("rank", _I), T.StructField("a", _L), T.StructField("b", _L), T.StructField("dist", _D)])
METRICS = T.StructType([T.StructField("stage", _S), T.StructField("round", _I), T.StructField("pairs", _L), T.StructField("seconds", _D)])
