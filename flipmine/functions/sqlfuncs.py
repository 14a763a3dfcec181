"""SQL functions and table functions of the library; ``register`` makes them known to a session."""

from __future__ import annotations

from collections.abc import Iterator
from typing import Any

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.functions import arrow_udf, udtf
from pyspark.sql.types import BinaryType

from ..config import FlipParams
from . import channel

#: Inlined by the optimizer, so they are folded and pushed like any expression.
SQL_FUNCTIONS = (
    """CREATE OR REPLACE TEMPORARY FUNCTION basic_privacy(s DOUBLE, p DOUBLE, q DOUBLE) RETURNS DOUBLE
    RETURN 100 * (1 - s * p * p / (s * p + (1 - s) * (1 - q)) - s * (1 - p) * (1 - p) / (s * (1 - p) + (1 - s) * q))""",
    """CREATE OR REPLACE TEMPORARY FUNCTION relative_error(s DOUBLE, p DOUBLE, q DOUBLE, dbsize BIGINT) RETURNS DOUBLE
    RETURN sqrt((p * (1 - p) + (1 / s - 1) * q * (1 - q)) / (s * dbsize)) / abs(p + q - 1)""",
    """CREATE OR REPLACE TEMPORARY FUNCTION estimate1(n BIGINT, dbsize BIGINT, p DOUBLE, q DOUBLE) RETURNS DOUBLE
    RETURN (n - (1 - q) * dbsize) / (p + q - 1)""",
)


@udtf(returnType="subset array<int>, size int")
class ItemsetSubsets:
    def eval(self, itemset: list[int]) -> Iterator[tuple[list[int], int]]:
        for code in range(1 << len(itemset)):
            part = [x for i, x in enumerate(itemset) if code >> i & 1]
            yield part, len(part)


@udtf(returnType="antecedent array<int>, consequent array<int>, confidence double")
class ItemsetRules:
    """Ways to split an itemset into two parts that are not empty.

    ``supports`` are those of all subsets, in order of the codes of their items' places from 0 (the empty set) on; without
    them confidences are null and ``min_conf`` has no effect. A part without support gives no rule.
    """

    def eval(self, itemset: list[int], supports: list[float] | None = None, min_conf: float = 0.0) -> Iterator[tuple[list[int], list[int], float | None]]:
        whole = (1 << len(itemset)) - 1
        for code in range(1, whole):
            confidence = None
            if supports:
                if not supports[code] or supports[code] <= 0:
                    continue
                confidence = supports[whole] / supports[code]
                if confidence < min_conf:
                    continue
            yield [x for i, x in enumerate(itemset) if code >> i & 1], [x for i, x in enumerate(itemset) if not code >> i & 1], confidence


@udtf(returnType="i int, j int, prob double")
class Transition:
    def eval(self, n: int, p: float, q: float) -> Iterator[tuple[int, int, float]]:
        for i, row in enumerate(channel.weight_matrix(n, p, q)):
            for j, prob in enumerate(row):
                yield i, j, float(prob)


@arrow_udf(BinaryType())
def bits_and(bits: pa.Array) -> Any:
    """AND of all bit vectors of a group; they are of one length, and nulls are passed over."""
    held = [np.frombuffer(b.as_py(), np.uint8) for b in bits if b.is_valid]
    return np.bitwise_and.reduce(held).tobytes() if held else None


def flip_bits(params: FlipParams, n_items: int, seed: int):  # noqa: ANN201
    """A function (bits, tid) of columns: the bit vector distorted where it is, by the draws of ``flip_bitvectors``."""
    from ..operators.distort import flipped_bits

    @arrow_udf(BinaryType())
    def flip(bits: pa.Array, tids: pa.Array) -> pa.Array:
        return pa.array([flipped_bits(raw.as_py(), tid.as_py(), n_items, params, seed) if raw.is_valid else None for raw, tid in zip(bits, tids, strict=True)], pa.binary())

    return flip


def register(spark: SparkSession, params: FlipParams | None = None, n_items: int = 0, seed: int = 0) -> None:
    """All functions; ``flip_bits`` only where the owner of the data gives the channel and the private seed."""
    from ..sources.generator import PatternSource

    spark.udf.register("bits_and", bits_and)
    if params:
        spark.udf.register("flip_bits", flip_bits(params, n_items, seed))

    for text in SQL_FUNCTIONS:
        spark.sql(text)
    spark.udtf.register("itemset_subsets", ItemsetSubsets)
    spark.udtf.register("itemset_rules", ItemsetRules)
    spark.udtf.register("transition", Transition)
    spark.dataSource.register(PatternSource)
