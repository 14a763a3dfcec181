"""Schemas of the engine's tables, made without a session."""

from pyspark.sql import types as T

_KINDS = {"long": T.LongType(), "int": T.IntegerType(), "double": T.DoubleType(), "string": T.StringType(), "binary": T.BinaryType(), "timestamp": T.TimestampType(), "array<int>": T.ArrayType(T.IntegerType())}


def _of(**fields: str) -> T.StructType:
    return T.StructType([T.StructField(name, _KINDS[kind]) for name, kind in fields.items()])


BASKET_LONG = _of(tid="long", item="int")
BASKET_ARRAY = _of(tid="long", items="array<int>")
BASKET_BITS = _of(tid="long", bits="binary")
COLUMN_BITS = _of(chunk="long", item="int", bits="binary")
ITEMS = _of(item="int", label="string")
CHANNEL = _of(p="double", q="double", n_items="int", dbsize="long")
COUNTS = _of(itemset="array<int>", k="int", n="long")
ESTIMATES = _of(itemset="array<int>", k="int", n="long", est="double")
RULES = _of(antecedent="array<int>", consequent="array<int>", support="double", confidence="double")
EVENTS = _of(event_id="long", ts="timestamp", user_id="long", event_type="string", value="double", props="string")
