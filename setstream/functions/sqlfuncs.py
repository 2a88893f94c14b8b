"""SQL functions, table functions and Arrow functions for users who work in SQL."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from .hashing import HashFamily


def register(spark: SparkSession, family: HashFamily, reserve: int = 8) -> None:
    """``sig_similarity(a, b)`` and ``band_probability(s, b, r)`` (inlined by the optimizer), ``signature_of(array)``,
    ``bands(sig, b, r)`` and ``fault_trace(seqs, elements, ops)``."""
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION sig_similarity(a ARRAY<BIGINT>, b ARRAY<BIGINT>) RETURNS DOUBLE "
        "RETURN aggregate(zip_with(a, b, (p, q) -> IF(p = q, 1, 0)), 0, (n, x) -> n + x) / size(a)"
    )
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION band_probability(s DOUBLE, b INT, r INT) RETURNS DOUBLE RETURN 1 - power(1 - power(s, r), b)")
    spark.udf.register("signature_of", signature_udf(family))
    spark.udtf.register("bands", Bands)
    spark.udtf.register("fault_trace", fault_trace(family, reserve))


def signature_udf(family: HashFamily):
    @F.pandas_udf("array<bigint>")
    def signature_of(elements: pd.Series) -> pd.Series:
        return pd.Series([None if e is None or not len(e) else family.pairs_numpy(np.asarray(e, np.int64)).min(0).tolist() for e in elements])

    return signature_of


@F.udtf(returnType="band INT, key STRING")
class Bands:
    """Bands of a signature and their text keys."""

    def eval(self, sig: list, b: int, r: int) -> Iterator[tuple[int, str]]:
        for i in range(b):
            yield i, "-".join(str(x) for x in sig[i * r : i * r + r])


def fault_trace(family: HashFamily, reserve: int):
    """A table function: the recoveries of one set's update sequence."""

    @F.udtf(returnType="seq BIGINT, slot INT, size_after BIGINT")
    class FaultTrace:
        def eval(self, seqs: list, elements: list, ops: list) -> Iterator[tuple[int, int, int]]:
            from ..operators.replay import kernel

            sketch = kernel("reserve", family, reserve)
            sketch.run(np.asarray(seqs, np.int64), np.asarray(elements, np.int64), np.asarray(ops))
            yield from sketch.log

    return FaultTrace


def reserve_agg_udf(family: HashFamily, reserve: int):
    """A grouped aggregate of elements to the flattened (k, reserve) matrix of least pairs, padded with the infinite pair."""

    @F.pandas_udf("array<bigint>")
    def reserve_agg(elements: pd.Series) -> list:
        from ..operators.replay import kernel

        sketch = kernel("reserve", family, reserve)
        sketch.start(elements.to_numpy(np.int64))
        return sketch.buffer.ravel().tolist()

    return reserve_agg
