"""References: a read's number and an offset in one 64-bit integer."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class RefLayout:
    stride: int = 1000

    @staticmethod
    def fit(max_len: int) -> RefLayout:
        """The next power of ten above the longest read."""
        stride = 10
        while stride <= max_len:
            stride *= 10
        return RefLayout(stride)

    def pack(self, read_id: Column, offset: Column) -> Column:
        return read_id.cast("long") * self.stride + offset

    def read_id(self, ref: Column) -> Column:
        return F.call_function("div", ref, F.lit(self.stride))

    def offset(self, ref: Column) -> Column:
        return F.pmod(ref, F.lit(self.stride))

    def sound(self, read_id: Column, seq: Column) -> Column:
        """seq, or a failure at run time where it or its number is null or doesn't fit this layout; costs nothing beside a scan."""
        far = ((1 << 63) - 1) // self.stride - 1
        fine = (F.length(seq) < self.stride) & read_id.between(0, far)
        return F.when(fine, seq).otherwise(F.raise_error(F.concat(F.lit("a read is null, numbered out of range, or as long as the stride or longer: "), F.lit(self.stride))))

    def check(self, reads: DataFrame) -> None:
        """Raises if a read is too long or too far out for this layout, or has no text."""
        worst = reads.agg(F.max(F.length("seq")).alias("n"), F.max("read_id").alias("id"), F.count_if(F.col("seq").isNull() | F.col("read_id").isNull()).alias("nulls")).first()
        if worst["nulls"]:
            raise ValueError("reads hold nulls")
        if (worst["n"] or 0) >= self.stride:
            raise ValueError(f"a read of {worst['n']} symbols needs a larger stride than {self.stride}")
        if (worst["id"] or 0) > ((1 << 63) - 1) // self.stride - 1:
            raise ValueError("a read's number is too large")
