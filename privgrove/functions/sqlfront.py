"""SQL and UDF surface: functions for spark.sql, a vectorised scorer, an aggregate and table functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import ArrayType, DoubleType, IntegerType, StructField, StructType

# Fixed texts: SQL functions that Catalyst inlines.
SQL_FUNCTIONS = {
    "laplace_from_uniform": "(u DOUBLE, scale DOUBLE) RETURNS DOUBLE RETURN -scale * signum(u - 0.5D) * ln(1 - 2 * abs(u - 0.5D))",
    "keyed_uniform": "(k STRING) RETURNS DOUBLE RETURN (CAST(conv(substr(sha2(k, 256), 1, 13), 16, 10) AS BIGINT) + 0.5D) / 4503599627370496.0D",
    "split_gain": "(gl DOUBLE, nl DOUBLE, gr DOUBLE, nr DOUBLE, lam DOUBLE) RETURNS DOUBLE RETURN gl * gl / (nl + lam) + gr * gr / (nr + lam)",
    "amplify_epsilon": "(eps DOUBLE, gamma DOUBLE) RETURNS DOUBLE RETURN log1p(gamma * expm1(eps))",
}


def register_sql(spark: SparkSession) -> None:
    """Create the temporary SQL functions; dp_laplace(value, scale, key) builds on them."""
    for name, body in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name} {body}")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION dp_laplace(x DOUBLE, scale DOUBLE, k STRING) RETURNS DOUBLE RETURN x + laplace_from_uniform(keyed_uniform(k), scale)")


def tree_predict(model):
    """A pandas UDF that scores a struct of bins (b_0, b_1, ..)."""
    from privgrove.plans.tree import routed

    packed = [(t.arrays(), t.depth()) for t in model.trees]

    @pandas_udf(DoubleType())
    def score(bins: pd.DataFrame) -> pd.Series:
        b = bins.to_numpy()
        return pd.Series(sum((a[5][routed(a, b, d)] for a, d in packed), np.zeros(len(b))))

    return score


@pandas_udf(ArrayType(DoubleType()))
def weighted_quartiles(value: pd.Series, weight: pd.Series) -> list:
    """Weighted quartiles of a group: the first value whose running weight reaches each quarter."""
    order = np.argsort(value.to_numpy(), kind="stable")
    v, w = value.to_numpy()[order], np.cumsum(weight.to_numpy()[order])
    return [float(v[np.searchsorted(w, q * w[-1])]) for q in (0.25, 0.5, 0.75)]


@udtf(returnType=StructType([StructField("slot", IntegerType()), StructField("cut", DoubleType())]))
class ProposeCuts:
    """Even cuts of a public range, as a table function."""

    def eval(self, lo: float, hi: float, count: int):
        for k in range(count):
            yield k, lo + (k + 1) * (hi - lo) / (count + 1)


def explained(spark: SparkSession, model):
    """The model's nodes as readable rows."""
    return spark.createDataFrame([(t, k, line) for t in range(len(model.trees)) for k, line in enumerate(model.explain(t))], "tree int, line int, text string")


def registered(spark: SparkSession) -> None:
    """SQL functions and the table function under their SQL names."""
    register_sql(spark)
    spark.udtf.register("propose_cuts", ProposeCuts)


def dp_laplace_column(x, scale: float, key):
    """dp_laplace as a column, for DataFrame code."""
    return F.call_function("dp_laplace", x, F.lit(scale), key)
