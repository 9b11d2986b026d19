"""User functions: for SQL text, for grouped aggregation, and a table function that decodes neighbourhoods."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: SQL bodies of the functions that need no Python.
SQL_FUNCTIONS = {
    "gpart_varint_len(x BIGINT) RETURNS INT": "1 + " + " + ".join(f"CAST(x >= {1 << 7 * n} AS INT)" for n in range(1, 9)),
    "gpart_zigzag(x BIGINT) RETURNS BIGINT": "CASE WHEN x >= 0 THEN 2 * x ELSE -2 * x - 1 END",
    "gpart_hash(x BIGINT) RETURNS BIGINT": "x * 48271 % 2147483647",
    "gpart_entry_width(u BIGINT) RETURNS INT": "CASE WHEN u < 256 THEN 8 WHEN u < 65536 THEN 16 WHEN u < 4294967296 THEN 32 ELSE 64 END",
}


def register(spark: SparkSession) -> None:
    """Makes the functions known to SQL text; they are inlined into plans."""
    for head, body in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")


@F.pandas_udf(T.DoubleType())
def geometric_mean(x: pd.Series) -> float:
    return float(np.exp(np.log(x).mean()))


@F.pandas_udf(T.DoubleType())
def harmonic_mean(x: pd.Series) -> float:
    return float(len(x) / (1 / x).sum())


def delta(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
    """Of one id: the sum of w on the left less that on the right."""
    key = (left if len(left) else right)["id"].iloc[0]
    return pd.DataFrame({"id": [key], "delta": [int(left["w"].sum()) - int(right["w"].sum())]})


@F.udtf(returnType=T.StructType([T.StructField(c, T.LongType()) for c in ("src", "dst", "w")]))
class DecodeNeighbors:
    """decode_neighbors(id, degree, payload, weighted): a row for each edge of a coded neighbourhood."""

    def eval(self, id: int, degree: int, payload: bytes, weighted: bool):
        from gpart.operators.codec import decode

        _, nbrs, wts = decode(id, degree, bytes(payload), weighted)
        for dst, w in zip(nbrs, wts, strict=True):
            yield id, dst, w


def decoded(spark: SparkSession, graph, below: int) -> DataFrame:
    """(src, dst) of the vertices below an id, by the table function in SQL text."""
    from gpart.operators.codec import compress, to_csr

    spark.udtf.register("decode_neighbors", DecodeNeighbors)
    compress(to_csr(graph)).where(F.col("id") < below).createOrReplaceTempView("gpart_coded")
    return spark.sql("SELECT n.src, n.dst FROM gpart_coded c, LATERAL decode_neighbors(c.id, c.degree, c.payload, false) n")
