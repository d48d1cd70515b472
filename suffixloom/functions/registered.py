"""The functions under SQL names, and a table function of suffixes."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


@udtf(returnType="offset: int, suffix: string")
class Suffixes:
    """SELECT * FROM suffixes('text'): every suffix, the empty one last."""

    def eval(self, text: str):
        if text is not None:
            for i in range(len(text) + 1):
                yield i, text[i:]


def register(spark: SparkSession, stride: int = 1000) -> None:
    spark.udtf.register("suffixes", Suffixes)
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION pack_ref(read_id BIGINT, off BIGINT) RETURNS BIGINT RETURN read_id * {stride} + off")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION ref_read(ref BIGINT) RETURNS BIGINT RETURN ref DIV {stride}")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION ref_offset(ref BIGINT) RETURNS BIGINT RETURN pmod(ref, {stride})")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION dna_code(t STRING, w INT) RETURNS BIGINT RETURN CAST(conv(rpad(translate(substring(t, 1, w), 'ACGT', '1234'), w, '0'), 5, 10) AS BIGINT)")
