"""SQL surface: functions and table functions for ``spark.sql``."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

FUNCTIONS = {
    "harmonic4": "(a DOUBLE, b DOUBLE, c DOUBLE, d DOUBLE) RETURNS DOUBLE RETURN CASE WHEN least(a, b, c, d) <= 0 THEN 0D ELSE 4 / (1 / a + 1 / b + 1 / c + 1 / d) END",
    "power_weight": "(x DOUBLE, n DOUBLE, k DOUBLE, a DOUBLE) RETURNS DOUBLE RETURN power(x, n) / (1 + exp(-k * (x - a)))",
    "band_weight": "(sim DOUBLE) RETURNS INT RETURN CASE WHEN sim >= 0.99 THEN 8 WHEN sim >= 0.98 THEN 7 WHEN sim >= 0.96 THEN 6 WHEN sim >= 0.95 THEN 5 WHEN sim >= 0.94 THEN 4 WHEN sim >= 0.92 THEN 3 WHEN sim >= 0.90 THEN 2 ELSE 0 END",
}


@udtf(returnType="pos int, gram string")
class Shingle:
    """shingle(text, n): word n-grams with their positions."""

    def eval(self, text: str, n: int):
        parts = (text or "").split()
        for i in range(len(parts) - n + 1):
            yield i, " ".join(parts[i : i + n])


@udtf(returnType="band int, key string")
class LshBand:
    """lsh_band(signature, bands, rows): the keys of a MinHash signature."""

    def eval(self, signature: list, bands: int, rows: int):
        for b in range(bands):
            yield b, ":".join(map(str, signature[b * rows : (b + 1) * rows]))


def register(spark: SparkSession) -> None:
    for name, body in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")
    spark.udtf.register("shingle", Shingle)
    spark.udtf.register("lsh_band", LshBand)
