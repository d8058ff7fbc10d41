"""SQL functions: the models as SQL bodies that Catalyst inlines."""

from __future__ import annotations

from pyspark.sql import SparkSession

BODIES = {
    "break_even_size": ("c_ipc DOUBLE, c_enc_ms DOUBLE, workers DOUBLE", "DOUBLE", "c_ipc * workers / c_enc_ms * 1000"),
    "call_seconds": ("n DOUBLE, c_ipc DOUBLE, c_enc_ms DOUBLE, workers DOUBLE", "DOUBLE", "c_ipc + n * c_enc_ms / 1000 / workers"),
    "predicted_speedup": ("alpha DOUBLE, calls DOUBLE, parts DOUBLE", "DOUBLE", "(1 + alpha) / (1 + alpha * calls / parts)"),
    "overlap_ratio": ("t_enc DOUBLE, t_ser DOUBLE, t_upl DOUBLE", "DOUBLE", "CASE WHEN t_ser + t_upl = 0 THEN 1 ELSE 1 - greatest(0, t_ser + t_upl - t_enc) / (t_ser + t_upl) END"),
    "recommend": ("phi DOUBLE, cv DOUBLE", "STRING", "CASE WHEN phi > 0.5 AND cv > 1 THEN 'strong' WHEN phi > 0.5 THEN 'beneficial' WHEN cv > 1 THEN 'moderate' ELSE 'optional' END"),
    "cost_per_million": ("wall DOUBLE, texts DOUBLE, dollars_per_hour DOUBLE", "DOUBLE", "wall * dollars_per_hour / 3600 * 1e6 / texts"),
}


def register(spark: SparkSession) -> list[str]:
    """Create the functions for this session; returns their names."""
    for name, (arguments, kind, body) in BODIES.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({arguments}) RETURNS {kind} RETURN {body}")
    return sorted(BODIES)
