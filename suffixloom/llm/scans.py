"""Sequential passes over array columns in column functions, linear in their length but for a small share."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Items to a block. Arrays grow by copying, so results gather in blocks, and only blocks in the whole.
BLOCK = 64


def bound(value: Column, body: Callable[[Column], Column]) -> Column:
    """body(value), with value computed once however often body names it."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def scan(items: Column, state: Column, step: Callable[[Column, Column], Column], emit: Callable[[Column, Column], Column], kind: str) -> Column:
    """An array of emit(state, item) for each item; state is what step(state, item) made of the items before.

    kind is the SQL type of what emit gives. Null items are left to step and emit; an empty array gives an empty one.
    """
    none = F.expr(f"cast(array() as array<{kind}>)")

    def within(start: Column, block: Column) -> Column:
        first = F.struct(start.alias("state"), none.alias("out"))
        return F.aggregate(block, first, lambda x, item: F.struct(step(x["state"], item).alias("state"), F.concat(x["out"], F.array(emit(x["state"], item))).alias("out")))

    def over(whole: Column) -> Column:
        blocks = F.transform(F.sequence(F.lit(0), F.floor((F.size(whole) - 1) / BLOCK).cast("int")), lambda k: F.slice(whole, k * BLOCK + 1, F.lit(BLOCK)))
        first = F.struct(state.alias("state"), F.expr(f"cast(array() as array<array<{kind}>>)").alias("outs"))
        joined = lambda x, done: F.struct(done["state"].alias("state"), F.concat(x["outs"], F.array(done["out"])).alias("outs"))
        return F.aggregate(blocks, first, lambda x, block: bound(within(x["state"], block), lambda done: joined(x, done)), lambda x: F.flatten(x["outs"]))

    return bound(items, lambda whole: F.when(F.size(whole) > 0, over(whole)).otherwise(none))
