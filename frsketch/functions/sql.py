"""The register functions for SQL users, and packed sketches as a table function; no Python at run time."""

from __future__ import annotations

from pyspark.sql import SparkSession

FUNCTIONS = {
    "frs_exponent(reg INT, r INT) RETURNS INT": "shiftright(reg, r)",
    "frs_mantissa(reg INT, r INT) RETURNS INT": "(1 << r) - 1 - (reg & ((1 << r) - 1))",
    "frs_pack(e INT, m INT, r INT) RETURNS INT": "e * (1 << r) + (1 << r) - 1 - m",
    "frs_decode(reg INT, q INT, r INT) RETURNS DOUBLE": "CASE WHEN shiftright(reg, r) < (1 << q) THEN pow(2D, -shiftright(reg, r)) * (1 + ((1 << r) - 1 - (reg & ((1 << r) - 1))) / CAST(1 << r AS DOUBLE)) ELSE ((1 << r) - 1 - (reg & ((1 << r) - 1))) * pow(2D, -(r + (1 << q) - 1)) END",
    "frs_bits(p INT, q INT, r INT) RETURNS BIGINT": "CAST(q + r AS BIGINT) << p",
    "frs_phi(n DOUBLE, m DOUBLE) RETURNS DOUBLE": "4 * n * m / ((n + m) * (n + m))",
}


TABLE_FUNCTION = """frs_registers(regs BINARY, width INT) RETURNS TABLE (bucket INT, reg INT) RETURN
SELECT i, v FROM (
  SELECT i, aggregate(sequence(width, 1, -1), 0, (a, j) -> a * 256 + CAST(conv(hex(substring(regs, i * width + j, 1)), 16, 10) AS INT)) AS v
  FROM (SELECT explode(sequence(0, length(regs) div width - 1)) AS i) WHERE length(regs) >= width
) WHERE v > 0"""


def register_functions(spark: SparkSession) -> None:
    """Temporary SQL functions: expressions that Catalyst inlines, no Python."""
    for head, body in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {TABLE_FUNCTION}")
