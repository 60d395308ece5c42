"""SQL names for the scalar helpers, and a table function for the cells a ball meets."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

SCALARS = {
    "peak_cell": ("x DOUBLE, shift DOUBLE, side DOUBLE", "BIGINT", "CAST(floor((x - shift) / side) AS BIGINT)"),
    "peak_cell_center": ("cell BIGINT, shift DOUBLE, side DOUBLE", "DOUBLE", "shift + (cell + 0.5D) * side"),
    "peak_near": ("x DOUBLE, y DOUBLE, u DOUBLE, v DOUBLE, reach DOUBLE", "BOOLEAN", "(x - u) * (x - u) + (y - v) * (y - v) <= reach * reach * (1 + 1e-9)"),
    "peak_cap": ("eps DOUBLE", "DOUBLE", "acos((3 * eps + eps * eps * eps) / (2 + 2 * eps * eps)) / pi()"),
}


@udtf(returnType="k0 bigint, k1 bigint")
class BallCells:
    """Cells of one grid within a unit of a centre in the plane."""

    def eval(self, x: float, y: float, shift_x: float, shift_y: float, side: float):
        import math

        for a in range(math.floor((x - shift_x - 1) / side), math.floor((x - shift_x + 1) / side) + 1):
            for b in range(math.floor((y - shift_y - 1) / side), math.floor((y - shift_y + 1) / side) + 1):
                dx = max(shift_x + a * side - x, 0.0, x - shift_x - (a + 1) * side)
                dy = max(shift_y + b * side - y, 0.0, y - shift_y - (b + 1) * side)
                if dx * dx + dy * dy <= 1 + 1e-9:
                    yield a, b


def register(spark: SparkSession) -> list[str]:
    """Make the names known to the session; the scalars are SQL expressions and stay in generated code."""
    for name, (inputs, kind, body) in SCALARS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({inputs}) RETURNS {kind} RETURN {body}")
    spark.udtf.register("peak_ball_cells", BallCells)
    return [*SCALARS, "peak_ball_cells"]
