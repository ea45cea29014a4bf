"""Functions of keys for SQL, and the Python forms of a histogram and of its buckets."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Temporary SQL functions; they are expressions, so they stay inside generated code.
SQL_FUNCTIONS = {
    "signed_key": "(v BIGINT) RETURNS STRING RETURN lpad(hex(v ^ (-9223372036854775807L - 1)), 16, '0')",
    "unsigned_key": "(v BIGINT) RETURNS STRING RETURN lpad(hex(v), 16, '0')",
    "text_key": "(t STRING, width INT) RETURNS STRING RETURN rpad(substring(hex(encode(t, 'UTF-8')), 1, 2 * width), 2 * width, '0')",
    "key_digit": "(k STRING, i INT) RETURNS STRING RETURN substring(k, 2 * i + 1, 2)",
    "descending_key": "(k STRING) RETURNS STRING RETURN translate(k, '0123456789ABCDEF', 'FEDCBA9876543210')",
}


@F.pandas_udf(T.ArrayType(T.LongType()))
def digit_counts(digits: pd.Series) -> list:
    """How often each of the 256 digit values (two hex characters) occurs in a group."""
    known = digits.dropna()
    values = np.frombuffer(bytes.fromhex("".join(known)), np.uint8) if len(known) else np.zeros(0, np.uint8)
    return np.bincount(values, minlength=256).tolist()


@F.udtf(returnType=T.StructType([T.StructField("prefix", T.StringType()), T.StructField("n", T.LongType()), T.StructField("start", T.LongType())]))
class BucketChildren:
    """The non-empty children of a bucket from its counts, with the offset of each."""

    def eval(self, prefix: str, counts: list) -> Iterator[tuple]:
        at = 0
        for value, n in enumerate(counts):
            if n:
                yield f"{prefix}{value:02X}", n, at
            at += n


def register(spark: SparkSession) -> None:
    """Make the functions known to SQL: signed_key, unsigned_key, text_key, key_digit, descending_key, digit_counts, bucket_children."""
    for name, body in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")
    spark.udf.register("digit_counts", digit_counts)
    spark.udtf.register("bucket_children", BucketChildren)
