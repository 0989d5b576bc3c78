"""Functions and views for SQL users."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

from ..operators.repair import IndexState
from ..operators.walks import crossings_of
from .params import PprParams


@udtf(returnType="step int, node long, next long")
class PprWalk:
    """Crossing rows of one path: SELECT * FROM ppr_walk(array(1, 2, 4))."""

    def eval(self, path):
        for i in range(len(path) - 1):
            yield i, path[i], path[i + 1]


def register(spark: SparkSession, p: PprParams) -> None:
    spark.udtf.register("ppr_walk", PprWalk)
    factor = (2 * p.epsilon / 3 + 2) / (p.epsilon * p.epsilon)
    double = lambda v: f"DOUBLE('{v!r}')"  # noqa: E731  (a plain literal would be a decimal)
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION ppr_omega(delta DOUBLE, p_f DOUBLE) RETURNS DOUBLE RETURN {double(factor)} * ln(2 / p_f) / delta")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION ppr_walks(residue DOUBLE) RETURNS BIGINT RETURN ceil(residue * {double(p.omega)})")


def views(state: IndexState, ppr: DataFrame | None = None) -> None:
    state.edges.createOrReplaceTempView("edges")
    state.walks.createOrReplaceTempView("walks")
    crossings_of(state.walks).createOrReplaceTempView("crossings")
    if ppr is not None:
        ppr.createOrReplaceTempView("ppr")
