"""Order-preserving numeric prefix codes, as native expressions.

A code is the first `width` symbols as a number; the end of the string ranks below all symbols, so a string that ends early is
filled up with zeros, and numeric order is the order of prefixes.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def max_prefix_width(base: int, bits: int) -> int:
    """Most symbols whose codes fit a signed integer of that many bits."""
    width = 0
    while base ** (width + 1) - 1 <= (1 << bits - 1) - 1:
        width += 1
    return width


@dataclass(frozen=True)
class Alphabet:
    """Symbols in ascending byte order; symbol i has rank i + 1, and rank 0 is the end of the string."""

    symbols: str

    @property
    def base(self) -> int:
        return len(self.symbols) + 1

    @staticmethod
    def learn(reads: DataFrame, seq_col: str = "seq") -> Alphabet:
        """The distinct symbols that occur: one partial aggregation, a row for each symbol."""
        rows = reads.select(F.explode(F.array_distinct(F.split(seq_col, ""))).alias("c")).where("c <> ''").distinct().collect()
        return Alphabet("".join(sorted(r["c"] for r in rows)))

    def sound(self, seq: Column) -> Column:
        """seq, or a failure at run time where it holds a symbol that has no rank."""
        return F.when(F.translate(seq, self.symbols, "") == "", seq).otherwise(F.raise_error(F.concat(F.lit("a read holds symbols beside "), F.lit(self.symbols))))

    def byte_ranks(self) -> np.ndarray | None:
        """The rank of each byte, where every symbol is one."""
        if not self.symbols.isascii():
            return None
        ranks = np.zeros(256, np.int64)
        ranks[list(self.symbols.encode())] = np.arange(1, self.base)
        return ranks

    def _digits(self) -> str:
        return "0123456789abcdefghijklmnopqrstuvwxyz"[1 : self.base]

    def fits(self, width: int, int_key: bool) -> None:
        """Raises if codes of that many symbols don't fit the key."""
        if width > max_prefix_width(self.base, 32 if int_key else 64):
            raise ValueError(f"{width} symbols of base {self.base} don't fit the key")

    #: Whether a code stands for a whole number of symbols, so that a tail may leave them out.
    whole_symbols = True

    @staticmethod
    def window(suffix: Column, begin: int, width: int) -> Column:
        """Units begin .. begin + width - 1 of a suffix, ready for encode()."""
        return F.substring(suffix, begin + 1, width)

    @staticmethod
    def units(window: Column) -> Column:
        return F.length(window)

    def encode(self, text: Column, width: int, int_key: bool = False) -> Column:
        """Code of the first width symbols; text must hold symbols of this alphabet only."""
        self.fits(width, int_key)
        head = F.substring(text, 1, width)
        if self.base <= 36:
            code = F.conv(F.rpad(F.translate(head, self.symbols, self._digits()), width, "0"), self.base, 10)
        else:
            rank = F.create_map(*(F.lit(x) for i, s in enumerate(self.symbols) for x in (s, i + 1)))
            chars = F.split(F.rpad(head, width, "\0"), "")
            code = F.aggregate(chars, F.lit(0).cast("long"), lambda a, c: a * self.base + F.coalesce(F.element_at(rank, c), F.lit(0)))
        return code.cast("int" if int_key else "long")

    def decode(self, code: Column, width: int) -> Column:
        """The symbols of a code, without the filling."""
        if self.base > 36:
            raise ValueError("decoding is written for bases up to 36")
        text = F.lpad(F.lower(F.conv(code.cast("string"), 10, self.base)), width, "0")
        return F.translate(F.regexp_replace(text, "0+$", ""), self._digits(), self.symbols)


class Bytes:
    """UTF-8 bytes as they are: up to 7 to a long. Codes of texts with NUL would be ambiguous; sound() refuses them."""

    base = 256
    whole_symbols = False

    @staticmethod
    def sound(seq: Column) -> Column:
        """seq, or a failure at run time where it holds NUL."""
        return F.when(~F.contains(seq, F.lit("\0")), seq).otherwise(F.raise_error(F.lit("a read holds NUL, which byte codes keep for the end")))

    @staticmethod
    def byte_ranks() -> np.ndarray:
        """Of a byte is itself."""
        return np.arange(256, dtype=np.int64)

    @staticmethod
    def fits(width: int, int_key: bool) -> None:
        if width > (3 if int_key else 7):
            raise ValueError("at most 7 bytes fit a long, 3 an int")

    @staticmethod
    def window(suffix: Column, begin: int, width: int) -> Column:
        return F.substring(F.encode(suffix, "utf-8"), begin + 1, width)

    @staticmethod
    def units(window: Column) -> Column:
        return F.octet_length(window)

    @staticmethod
    def encode(text: Column, width: int, int_key: bool = False) -> Column:
        Bytes.fits(width, int_key)
        head = F.hex(F.substring(text.cast("binary"), 1, width))
        return F.conv(F.rpad(head, 2 * width, "0"), 16, 10).cast("int" if int_key else "long")


DNA = Alphabet("ACGT")
#: With the symbol that sequencers write for a base they could not tell.
DNA_N = Alphabet("ACGNT")


def prefix_key(text: Column, width: int) -> Column:
    """The baseline's key: the first symbols as text."""
    return F.substring(text, 1, width)
