"""Column expressions shared by the operators that use SQL functions alone."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """body(value) with value computed once: as a lambda variable it is not computed again for every element."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def literal_rows(spark: SparkSession, rows: list[tuple], names: list[str]) -> DataFrame:
    """A small table made of literals inside the plan."""
    structs = [F.struct(*[F.lit(x).alias(n) for x, n in zip(row, names, strict=True)]) for row in rows]
    return spark.range(1).select(F.explode(F.array(*structs)).alias("row")).select("row.*")


def matches(text: Column, pattern: str) -> Column:
    """Leftmost non-overlapping matches as structs (start, stop, m): code points from 0, stop exclusive.

    The pattern must not match the empty string. The texts between matches give the positions.
    """
    parts = F.struct(F.regexp_extract_all(text, F.lit(pattern), F.lit(0)).alias("found"), F.split(text, pattern, -1).alias("between"))
    none = F.array().cast("array<struct<start:int,stop:int,m:string>>")

    def step(acc: Column, z: Column) -> Column:
        start = acc["at"] + F.length(z["between"])
        stop = start + F.coalesce(F.length(z["found"]), F.lit(0))
        one = F.struct(start.alias("start"), stop.alias("stop"), z["found"].alias("m"))
        return F.struct(stop.alias("at"), F.when(z["found"].isNull(), acc["out"]).otherwise(F.concat(acc["out"], F.array(one))).alias("out"))

    return let(parts, lambda s: F.when(F.size(s["found"]) == 0, none).otherwise(F.aggregate(F.arrays_zip(s["found"].alias("found"), s["between"].alias("between")), F.struct(F.lit(0).alias("at"), none.alias("out")), step, lambda acc: acc["out"])))
