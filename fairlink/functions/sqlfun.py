"""SQL functions of the method, inlined by the optimiser, and a table function."""

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


@udtf(returnType="token: string")
class Tokens:
    """Substrings of q characters of a text."""

    def eval(self, text: str, q: int):
        value = (text or "").lower()
        for i in range(len(value) - q + 1):
            yield (value[i : i + q],)


def register(spark: SparkSession) -> None:
    """fl_dice, fl_laplace and fl_tokens for SQL users."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION fl_dice(a BIGINT, b BIGINT) RETURNS DOUBLE RETURN CASE WHEN bit_count(a) + bit_count(b) = 0 THEN 0D ELSE 2D * bit_count(a & b) / (bit_count(a) + bit_count(b)) END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION fl_laplace(u DOUBLE, s DOUBLE) RETURNS DOUBLE RETURN -s * signum(u - 0.5D) * ln(1D - 2D * abs(u - 0.5D))")
    spark.udtf.register("fl_tokens", Tokens)
