"""Fixed schemas of the tables the engine exchanges."""

from pyspark.sql import types as T

#: Stands for an infinite limit; packed pairs are below it.
INFINITE = 9223372036854775807

MEMBERS = "set_id BIGINT, element BIGINT"
UPDATES = "seq BIGINT, set_id BIGINT, element BIGINT, op INT"
SLOT = "STRUCT<pairs: ARRAY<BIGINT>, lim: BIGINT>"
RESERVE = f"set_id BIGINT, slots ARRAY<{SLOT}>"
SIGNATURES = "set_id BIGINT, sig ARRAY<BIGINT>"
BINS = "set_id BIGINT, level INT, bin INT, cnt BIGINT"
FAULTS = "set_id BIGINT, seq BIGINT, slot INT, size_after BIGINT"
PAIRS = "a BIGINT, b BIGINT, est DOUBLE"

EVENTS = T.StructType(
    [
        T.StructField("event_id", T.LongType()),
        T.StructField("ts", T.TimestampType()),
        T.StructField("user_id", T.LongType()),
        T.StructField("event_type", T.StringType()),
        T.StructField("value", T.DoubleType()),
        T.StructField("props", T.StringType()),
    ]
)
