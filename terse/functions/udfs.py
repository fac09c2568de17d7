"""The Python function surface: scalar, grouped, cogrouped and table functions over Arrow, and SQL registration."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from terse.sources.tables import read

QUERIES: dict = {}
SQL: dict[str, str] = {}

_GRID = "CAST(floor(CAST(e AS DOUBLE) * 1048576 + 0.5) AS BIGINT)"
_LONG = f"SELECT vec_id, label, coord, {_GRID} AS v FROM (SELECT vec_id, label, unnest(embedding) AS e, unnest(range(0, len(embedding))) AS coord FROM embeddings)"


def _whole(e) -> np.ndarray:
    return np.floor(np.asarray(e, float) * 1048576 + 0.5).astype(np.int64)


def largest(v: pd.Series) -> pd.Series:
    return v.map(lambda e: int(np.abs(_whole(e)).max())).astype("int64")


def register_all(spark: SparkSession) -> None:
    """SQL names of the vector functions."""
    spark.udf.register("terse_largest", F.pandas_udf(largest, "bigint"))


SQL["udf_scalar_arrow"] = SQL["udf_sql_registered"] = f"SELECT vec_id, max(abs(v)) AS top FROM ({_LONG}) GROUP BY vec_id"
QUERIES["udf_scalar_arrow"] = lambda s, d: read(s, d, "embeddings").select("vec_id", F.pandas_udf(largest, "bigint")("embedding").alias("top"))


def _registered(s, d):
    register_all(s)
    return s.sql("select vec_id, terse_largest(embedding) as top from {e}", e=read(s, d, "embeddings"))


QUERIES["udf_sql_registered"] = _registered


def _grouped(s, d):
    def norm(v: pd.Series) -> int:
        return int(sum(int((_whole(e) ** 2).sum()) for e in v))

    return read(s, d, "embeddings").groupBy("label").agg(F.pandas_udf(norm, "bigint", F.PandasUDFType.GROUPED_AGG)("embedding").alias("norm2"))


SQL["udf_grouped_agg"] = f"SELECT label, CAST(sum(v * v) AS BIGINT) AS norm2 FROM ({_LONG}) GROUP BY label"
QUERIES["udf_grouped_agg"] = _grouped


def _cogrouped(s, d):
    """State and gradients of a worker meet: here counts of two tables per nation."""
    a = read(s, d, "customer", "c_custkey", "c_nationkey").withColumnRenamed("c_nationkey", "nation")
    b = read(s, d, "supplier", "s_suppkey", "s_nationkey").withColumnRenamed("s_nationkey", "nation")

    def both(x: pa.Table, y: pa.Table) -> pa.Table:
        nation = (x if len(x) else y).column("nation")[0].as_py()
        return pa.table({"nation": pa.array([nation], pa.int32()), "customers": pa.array([len(x)], pa.int64()), "suppliers": pa.array([len(y)], pa.int64())})

    return a.groupBy("nation").cogroup(b.groupBy("nation")).applyInArrow(both, "nation int, customers bigint, suppliers bigint")


SQL["udf_cogrouped"] = "SELECT coalesce(a.k, b.k) AS nation, coalesce(a.n, 0) AS customers, coalesce(b.n, 0) AS suppliers FROM (SELECT c_nationkey AS k, count(*) AS n FROM customer GROUP BY 1) a FULL JOIN (SELECT s_nationkey AS k, count(*) AS n FROM supplier GROUP BY 1) b ON a.k = b.k"
QUERIES["udf_cogrouped"] = _cogrouped


def _table(s, d):
    @F.udtf(returnType="coord bigint, v bigint")
    class Coordinates:
        def eval(self, vector):
            for i, x in enumerate(_whole(vector).tolist()):
                yield i, x

    s.udtf.register("terse_coordinates", Coordinates)
    read(s, d, "embeddings", "vec_id", "embedding").createOrReplaceTempView("terse_vectors")
    return s.sql("select vec_id, coord, v from terse_vectors, lateral terse_coordinates(embedding)")


SQL["udf_table"] = f"SELECT vec_id, coord, v FROM ({_LONG})"
QUERIES["udf_table"] = _table
