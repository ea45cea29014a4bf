"""Chooses how to sort by what fits into memory, and runs it."""

from __future__ import annotations

import functools
import operator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..memory import Held
from .external import external_sort
from .msd import adaptive_sort, named


def choose_mode(bytes_in: int, budget: int, out_factor: float = 1.0) -> str:
    """internal if input and output fit, partial if the input alone does, else external."""
    if bytes_in * (1 + out_factor) <= budget:
        return "internal"
    return "partial" if bytes_in <= budget else "external"


def input_bytes(df: DataFrame) -> int:
    """The optimiser's size of the plan."""
    return int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))


def measured_bytes(df: DataFrame) -> DataFrame:
    """One row, ``bytes``: what the values of df hold, by reading them all; at least 1, as in the optimiser's size.

    Texts and binaries count by their bytes, other plain types by Spark's size of them, nested ones as JSON, nulls not at all.
    """
    spark_types = df._jdf.schema()
    sizes = []
    for i, field in enumerate(df.schema.fields):
        value, kind = F.col(f"`{field.name}`"), field.dataType
        if isinstance(kind, T.StringType | T.BinaryType):
            size = F.octet_length(value)
        elif isinstance(kind, T.ArrayType | T.MapType | T.StructType):
            size = F.octet_length(F.to_json(F.struct(value)))
        else:
            size = F.lit(spark_types.apply(i).dataType().defaultSize())
        sizes.append(F.when(value.isNotNull(), size).otherwise(0).cast("long"))
    return df.agg(F.greatest(F.coalesce(F.sum(functools.reduce(operator.add, sizes)), F.lit(0)), F.lit(1)).alias("bytes"))


def internal_sort(df: DataFrame, key: str, ptr: list[str], **options) -> DataFrame:
    """Everything in one pass; nothing is stored but the small bucket tree."""
    return adaptive_sort(df, key, ptr, **options)


def partial_sort(df: DataFrame, key: str, ptr: list[str], **options) -> DataFrame:
    """Pairs of key and pointer stay in memory while ranges are cut, and are let go before the output takes their place.

    The payload is read again for the one exchange; each range sorts its pairs and takes the payload in
    that order in its own task.
    """
    with Held(df.select(*named(list(dict.fromkeys([key, *ptr]))))) as pairs:
        return adaptive_sort(df, key, ptr, counted=pairs, **{"kernel": "msd", **options})


def sort(df: DataFrame, key: str, ptr: list[str], budget: int | None = None, mode: str = "auto", **options) -> DataFrame:
    """The whole order of df, by the path that the budget asks for; without one, Spark's executor memory decides."""
    if mode == "auto":
        if budget is None:
            status = df.sparkSession.sparkContext._jsc.sc().getExecutorMemoryStatus().values()
            budget = sum(int(part._1()) for part in (status.toSeq().apply(i) for i in range(status.size())))
        mode = choose_mode(input_bytes(df), budget)
    return {"internal": internal_sort, "partial": partial_sort, "external": external_sort}[mode](df, key, ptr, **options)
