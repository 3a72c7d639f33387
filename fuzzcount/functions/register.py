"""The lane functions as SQL functions: plain SQL bodies, so plans stay in generated code."""

from __future__ import annotations

from pyspark.sql import SparkSession

_PARAMS = ", ".join(f"{side}{i} BIGINT" for side in "ab" for i in range(4))
_HAMMING = " + ".join(f"bit_count(a{i} ^ b{i})" for i in range(4))
_COMMON = " + ".join(f"bit_count(a{i} & b{i})" for i in range(4))
_SIZES = " + ".join(f"bit_count({side}{i})" for side in "ab" for i in range(4))

FUNCTIONS = {
    "fc_hamming": (_PARAMS, "INT", _HAMMING),
    "fc_dice": (_PARAMS, "DOUBLE", f"CASE WHEN {_SIZES} = 0 THEN 0D ELSE 2D * ({_COMMON}) / ({_SIZES}) END"),
    "fc_eta": ("epsilon DOUBLE", "DOUBLE", "1D / (1D + exp(epsilon))"),
    "fc_num": ("t STRING", "BIGINT", "CAST(conv(substring(md5(t), 1, 8), 16, 10) AS BIGINT)"),
}


def register(spark: SparkSession) -> None:
    """Create the functions for this session."""
    for name, (params, kind, body) in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({params}) RETURNS {kind} RETURN {body}")
