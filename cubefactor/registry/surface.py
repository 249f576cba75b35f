"""What users of SQL see: temporary views of a tensor, an Arrow function and an aggregate."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import udfs
from ..functions.init import hash_factors
from ..operators.tensor import portable_sql
from ..sources import views
from ..sources.catalog import RECIPES, cells_sql, tensor
from ..sources.tables import load
from .common import rounded

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}


def view_counts(spark, sf):
    """Rows and heaviest row of each mode, asked of the registered views."""
    views.register(spark, tensor(spark, sf, "events3"), "events3_cells")
    return spark.sql("SELECT mode, count(*) AS n_rows, max(nnz) AS most FROM events3_cells_counts GROUP BY mode")


QUERIES["view_counts"] = view_counts
_COUNTS = " UNION ALL ".join(f"SELECT {n} AS mode, count(*) AS nnz FROM cells GROUP BY i{n}" for n in range(1, RECIPES["events3"].n_modes + 1))
ORACLE_SQL["view_counts"] = f"WITH cells AS MATERIALIZED ({cells_sql('events3')}), counts AS ({_COUNTS}) SELECT mode, count(*) AS n_rows, max(nnz) AS most FROM counts GROUP BY mode"


def arrow_dot_rows(spark, sf):
    """Squared length of each factor row of a mode, by the Arrow function."""
    rows = hash_factors(spark, tensor(spark, sf, "events3").dims, 3).where("mode = 1")
    return rows.select("idx", rounded(udfs.arrow_dot("f", "f")).alias("squared"))


QUERIES["arrow_dot_rows"] = arrow_dot_rows
_SQUARED = " + ".join(f"power({portable_sql('idx', 1, k)}, 2)" for k in range(3))
ORACLE_SQL["arrow_dot_rows"] = f"SELECT idx, round({_SQUARED}, 6) + 0.0 AS squared FROM (SELECT DISTINCT i1 AS idx FROM ({cells_sql('events3')}))"


def rmse_by_user(spark, sf):
    """Error of a constant guess for each user and day, by the pandas aggregate."""
    events = load(spark, sf, "events").where("value IS NOT NULL")
    return events.groupBy("user_id", F.dayofmonth("ts").alias("day")).agg(rounded(udfs.rmse_of(F.col("value"), F.lit(50.0))).alias("rmse"))


QUERIES["rmse_by_user"] = rmse_by_user
ORACLE_SQL["rmse_by_user"] = "SELECT user_id, CAST(day(ts) AS INT) AS day, round(sqrt(avg(power(value - 50, 2))), 6) + 0.0 AS rmse FROM events WHERE value IS NOT NULL GROUP BY 1, 2"
