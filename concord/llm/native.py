"""Small building blocks of JVM-side column expressions."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

BLOCK = 128


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of a value that is evaluated once, also where the body uses it inside other lambdas."""
    return F.element_at(F.transform(F.array(value), body), 1)


def starts(lengths: Column) -> Column:
    """Exclusive prefix sums of an array of ints, by blocks, so that long arrays don't cost the square of their size."""
    blocks = F.when(F.size(lengths) == 0, F.array().cast("array<int>")).otherwise(F.sequence(F.lit(0), F.floor((F.size(lengths) - 1) / BLOCK).cast("int")))
    total = lambda a: F.aggregate(a, F.lit(0), lambda x, y: x + y)
    sums = F.transform(blocks, lambda b: total(F.slice(lengths, b * BLOCK + 1, BLOCK)))
    offsets = F.aggregate(sums, F.array(F.lit(0)), lambda acc, s: F.array_append(acc, F.element_at(acc, -1) + s))
    return let(
        offsets,
        lambda o: F.transform(lengths, lambda _, i: F.get(o, F.floor(i / BLOCK).cast("int")) + total(F.slice(lengths, F.floor(i / BLOCK).cast("int") * BLOCK + 1, i % BLOCK))),
    )


def matches(text: Column, pattern: str, group: int | None = None) -> Column:
    """Leftmost non-overlapping matches as array<struct<start, end, text, value>>, offsets in code points, value the text of ``group``.

    The pieces between the matches and the matches themselves alternate, so their lengths give the offsets.
    """
    found = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    values = F.regexp_extract_all(text, F.lit(pattern), F.lit(group)) if group else found
    both = F.struct(F.split(text, pattern, -1).alias("gaps"), found.alias("found"), values.alias("values"))

    def placed(b: Column) -> Column:
        sizes = F.transform(b["found"], lambda m, i: F.length(F.get(b["gaps"], i)) + F.length(m))
        return let(
            F.struct(sizes.alias("sizes"), b.alias("b")),
            lambda s: let(
                F.struct(starts(s["sizes"]).alias("at"), s.alias("s")),
                lambda p: F.transform(
                    p["s"]["b"]["found"],
                    lambda m, i: F.struct(
                        (F.get(p["at"], i) + F.get(p["s"]["sizes"], i) - F.length(m)).alias("start"),
                        (F.get(p["at"], i) + F.get(p["s"]["sizes"], i)).alias("end"),
                        m.alias("text"),
                        F.get(p["s"]["b"]["values"], i).alias("value"),
                    ),
                ),
            ),
        )

    none = F.array().cast("array<struct<start:int,end:int,text:string,value:string>>")
    return F.when(text.rlike(pattern), let(both, placed)).otherwise(none)
