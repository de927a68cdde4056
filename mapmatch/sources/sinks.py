"""Sinks: verdicts, hits, compiled automata for reuse, and streams."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..automata.alphabet import SymbolClasses
from ..automata.dfa import Dfa
from ..automata.maps import MapAutomaton


def write_verdicts(df: DataFrame, path: str, by: str | None = None, mode: str = "error") -> None:
    writer = df.write.mode(mode)
    (writer.partitionBy(by) if by else writer).parquet(path)


def stream_verdicts(df: DataFrame, path: str, checkpoint: str):
    """Append finished verdicts of a stream to Parquet files."""
    return df.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).outputMode("append").start()


def save_automaton(spark: SparkSession, auto: MapAutomaton, path: str) -> None:
    """Write classes, base automaton and maps as three small tables."""
    classes = auto.base.classes
    spark.createDataFrame([(lo, hi, c, classes.unit) for lo, hi, c in classes.rows()], "lo int, hi int, cls int, unit string").coalesce(1).write.parquet(f"{path}/classes")
    rows = [(q, row, bool(f)) for q, (row, f) in enumerate(zip(auto.base.delta.tolist(), auto.base.final.tolist(), strict=True))]
    spark.createDataFrame(rows, "state int, next array<int>, final boolean").coalesce(1).write.parquet(f"{path}/states")
    rows = [(m, row, bool(f), int(p), int(v)) for m, (row, f, p, v) in enumerate(zip(auto.delta.tolist(), auto.final.tolist(), auto.parent, auto.via, strict=True))]
    spark.createDataFrame(rows, "map_id int, next array<int>, final boolean, parent int, via_cls int").write.parquet(f"{path}/maps")


def load_automaton(spark: SparkSession, path: str) -> MapAutomaton:
    c = spark.read.parquet(f"{path}/classes").orderBy("lo").collect()
    classes = SymbolClasses(c[0]["unit"], tuple(r["lo"] for r in c), tuple(r["cls"] for r in c))
    s = spark.read.parquet(f"{path}/states").orderBy("state").collect()
    dfa = Dfa(np.array([r["next"] for r in s], np.int32), np.array([r["final"] for r in s]), classes)
    m = spark.read.parquet(f"{path}/maps").orderBy("map_id").collect()
    return MapAutomaton(dfa, np.array([r["next"] for r in m], np.int32), np.array([r["final"] for r in m]), np.array([r["parent"] for r in m]), np.array([r["via_cls"] for r in m]))


def map_states(spark: SparkSession, auto: MapAutomaton) -> DataFrame:
    """map_id, image, final, parent, via_cls of a map automaton over a deterministic one."""
    rows = [(m, [int(q) for q in auto.image(m)], bool(auto.final[m]), int(auto.parent[m]), int(auto.via[m])) for m in range(auto.size)]
    return spark.createDataFrame(rows, "map_id int, image array<int>, final boolean, parent int, via_cls int")


def map_delta(spark: SparkSession, auto: MapAutomaton) -> DataFrame:
    """map_id, cls, next: the transition table as rows."""
    rows = spark.createDataFrame([(m, row) for m, row in enumerate(auto.delta.tolist())], "map_id int, next array<int>")
    return rows.select("map_id", F.posexplode("next").alias("cls", "next"))
