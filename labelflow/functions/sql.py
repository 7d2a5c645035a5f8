"""SQL functions for sketches, registered in a session; all are inlined to built-in expressions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .sketch import SketchSpec


def register(spark: SparkSession, spec: SketchSpec) -> None:
    """lf_hash(key, a, b, w), lf_estimate(block, cells) and the table functions lf_cells(key, val), lf_explode(block)."""
    pairs = ", ".join(f"struct(cast({j * spec.width} + (key * {a} + {b}) % {spec.prime} % {spec.width} as int) as cell, val as val)" for j, (a, b) in enumerate(zip(spec.a, spec.b)))
    for text in (
        f"CREATE OR REPLACE TEMPORARY FUNCTION lf_hash(k BIGINT, a BIGINT, b BIGINT, w BIGINT) RETURNS BIGINT RETURN (k * a + b) % {spec.prime} % w",
        "CREATE OR REPLACE TEMPORARY FUNCTION lf_estimate(s ARRAY<DOUBLE>, c ARRAY<INT>) RETURNS DOUBLE RETURN array_min(transform(c, i -> s[i]))",
        f"CREATE OR REPLACE TEMPORARY FUNCTION lf_cells(key BIGINT, val DOUBLE) RETURNS TABLE (cell INT, val DOUBLE) RETURN SELECT * FROM (SELECT inline(array({pairs})))",
        "CREATE OR REPLACE TEMPORARY FUNCTION lf_explode(s ARRAY<DOUBLE>) RETURNS TABLE (cell INT, val DOUBLE) RETURN SELECT pos, col FROM (SELECT posexplode(s)) WHERE col != 0",
    ):
        spark.sql(text)


def vector_sum(df: DataFrame, by: list[str], block: str, weight: Column) -> DataFrame:
    """The weighted sum of arrays for each group, by the JVM aggregate of the machine-learning library."""
    from pyspark.ml.functions import array_to_vector, vector_to_array
    from pyspark.ml.stat import Summarizer

    return df.groupBy(*by).agg(vector_to_array(Summarizer.sum(array_to_vector(F.col(block)), weight)).alias(block))


def cells_udtf(spec: SketchSpec):
    """A Python table function (key, val) -> (cell, val): the same rows as lf_cells, to compare with it."""
    from pyspark.sql.functions import udtf

    class Cells:
        def eval(self, key: int, val: float):
            for row in range(spec.depth):
                yield spec.cell_index(key, row), val

    return udtf(Cells, returnType="cell int, val double")


def vector_sum_arrow(df: DataFrame, by: str, block: str, weight: str) -> DataFrame:
    """As :func:`vector_sum` with a literal weight column, by a grouped function over Arrow tables, to compare with it."""
    import numpy as np
    import pyarrow as pa

    def total(t: pa.Table) -> pa.Table:
        held = np.array(t[block].to_pylist())
        return pa.table({by: t[by].slice(0, 1), block: pa.array([held.T @ t[weight].to_numpy()], pa.list_(pa.float64()))})

    return df.select(by, block, weight).groupBy(by).applyInArrow(total, f"{by} {dict(df.dtypes)[by]}, {block} array<double>")
