"""SQL names for the expressions: SQL functions, which Catalyst inlines, one Arrow function and one table function."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from linkveil.functions import crypto
from linkveil.functions.text import PAD


def _mask(left: pd.Series, right: pd.Series) -> pd.Series:
    from linkveil.operators.oracle import _aligned

    return pd.Series([_aligned(a, b) for a, b in zip(left, right, strict=True)])


class GramRows:
    """Rows of padded bigrams of a value."""

    def eval(self, value: str):
        if value:
            padded = PAD + value + PAD
            for gram in dict.fromkeys(padded[i : i + 2] for i in range(len(padded) - 1)):
                yield (gram,)


def register(spark: SparkSession) -> None:
    """Temporary functions of the session: lv_ramp, lv_dice, lv_hmac, lv_grams, lv_mask, lv_gram_rows."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION lv_ramp(sim DOUBLE, t DOUBLE) RETURNS DOUBLE RETURN round(0.5D * (1 + least(1.0D, abs(sim - t) / CASE WHEN sim < t THEN 0.05D ELSE 0.1D END)), 9)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION lv_dice(common BIGINT, a BIGINT, b BIGINT) RETURNS DOUBLE RETURN try_divide(2.0D * common, a + b)")
    block = f"rpad(CASE WHEN octet_length(secret) > {crypto.BLOCK} THEN sha2(secret, 256) ELSE hex(secret) END, {2 * crypto.BLOCK}, '0')"
    pad = lambda byte: f"unhex(array_join(transform(sequence(0, {crypto.BLOCK - 1}), i -> lpad(hex(CAST(conv(substr({block}, 1 + 2 * i, 2), 16, 10) AS INT) ^ {byte}), 2, '0')), ''))"
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION lv_hmac(message STRING, secret STRING) RETURNS STRING RETURN "
        f"sha2(concat({pad(crypto.OUTER)}, unhex(sha2(concat({pad(crypto.INNER)}, CAST(message AS BINARY)), 256))), 256)"
    )
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION lv_grams(value STRING) RETURNS ARRAY<STRING> RETURN array_distinct(transform(sequence(1, length(value) + 1), i -> substr('{PAD}' || value || '{PAD}', i, 2)))")
    spark.udf.register("lv_mask", F.pandas_udf(_mask, T.StringType()))
    spark.udtf.register("lv_gram_rows", F.udtf(GramRows, returnType=T.StructType([T.StructField("gram", T.StringType())])))
