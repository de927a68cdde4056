"""Map closure as a distributed iteration, for automata whose maps no longer fit one machine.

Each level is one explode over the classes and one anti-join with the maps already known, on a 256-bit digest of the
image, and is written to reliable storage before the next. The number of rounds is the depth of the search, so this
is not the way for ordinary patterns.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..automata.dfa import Dfa, TooLarge
from ..sources.shared import reliable


def close_distributed(spark: SparkSession, dfa: Dfa, most: int = 1_000_000_000) -> DataFrame:
    """image, final, level of every reachable map."""
    columns = F.array(*[F.array(*[F.lit(int(q)) for q in dfa.delta[:, c]]) for c in range(dfa.classes.k)])
    final = F.array(*[F.lit(bool(f)) for f in dfa.final])
    digest = lambda image: F.sha2(F.array_join(image, ","), 256)
    frontier = spark.range(1).select(F.array(*[F.lit(q) for q in range(dfa.size)]).cast("array<int>").alias("image"), F.lit(0).alias("level")).withColumn("digest", digest(F.col("image")))
    known, size, level = reliable(frontier), 1, 0
    frontier = known
    while True:
        level += 1
        step = frontier.select("image", F.explode(columns).alias("column")).select(F.transform("image", lambda q: F.element_at(F.col("column"), q + 1)).alias("image"))
        step = step.withColumn("digest", digest(F.col("image"))).dropDuplicates(["digest"])
        frontier = reliable(step.join(known, "digest", "left_anti").select("image", F.lit(level).alias("level"), "digest"))
        fresh = frontier.count()
        if not fresh:
            return known.select("image", F.element_at(final, F.element_at("image", 1) + 1).alias("final"), "level")
        size += fresh
        if size > most:
            raise TooLarge(f"more than {most} maps")
        known = reliable(known.unionByName(frontier)) if level % 8 == 0 else known.unionByName(frontier)
