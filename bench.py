"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS], and the experiments; prints one JSON line.

Queries run to the noop sink after a warm-up, compile time of automata excluded, as the published figures exclude it.
``kernels`` holds symbols a second of one core over class ids in memory (map table, sequential table, speculation, the
distinct maps a word touches) and build times. ``scaling`` runs words of $BENCH_SYMBOLS symbols (default 2**27) on Spark:
seconds and speed-up over one task with the sequential table, by tasks at once, and a word of eight times that size (1 GB)
by all tasks; text is cached first. ``small_inputs`` has seconds of both ways for growing words, job start and fold
included, and the size from which two tasks stay ahead.
"""

from __future__ import annotations

import json
import os
import sys
import time

import numpy as np


def _session(cpus: str):
    from pyspark.sql import SparkSession

    settings = {"spark.sql.shuffle.partitions": cpus, "spark.driver.memory": "12g", "spark.ui.enabled": "false", "spark.sql.session.timeZone": "UTC", "spark.ui.showConsoleProgress": "false"}
    return SparkSession.builder.master(f"local[{cpus}]").config(map=settings).getOrCreate()


def _queries() -> dict:
    from mapmatch.plans.workloads import QUERIES

    names = [
        "doc_email_rows", "doc_email_chunked_inorder", "doc_email_chunked_tree", "doc_email_lazy", "doc_email_speculative", "doc_email_nfa_maps",
        "doc_email_rlike", "page_url_shape", "user_funnel", "order_flag_parity", "customer_status_runs", "digit_word_r5", "digit_word_r50", "digit_word_ra", "benchmark_leaks", "match_end_counts",
    ]
    return {n: QUERIES[n] for n in names}


def _classes(c, period: str, size: int) -> np.ndarray:
    return np.resize(c.dfa.classes.table[[ord(x) for x in period]], size).astype(np.uint8)


def _kernels(compiled: dict) -> dict:
    from mapmatch.operators.measure import maps_touched, scan_rate, size_report
    from mapmatch.plans.corpora import alternating, loop, loop_or_run

    out: dict = {}
    for name, n, lanes in (("r5", 5, 4096), ("r50", 50, 4096), ("r500", 500, 4096)):
        c = compiled[name]
        word = _classes(c, "1" * n + "7" * n, 4000 * lanes)  # every lane begins at a period
        short = _classes(c, "1" * n + "7" * n, 400 * 1024)  # D times the work
        out[name] = {"maps_per_s": scan_rate(c, word, lanes), "dfa_per_s": scan_rate(c, word, lanes, "dfa"), "speculate_per_s": scan_rate(c, short, 1024, "speculate", 1), "maps_touched": maps_touched(c, word[:4000])}
    c = compiled["ra500"]
    word = _classes(c, "a", 1 << 24)
    out["ra500"] = {"maps_per_s": scan_rate(c, word, 4096), "maps_touched": maps_touched(c, word[:4000])}
    for name, p in (("r5", loop(5)), ("r50", loop(50)), ("r500", loop(500)), ("ra500", loop_or_run(500)), ("alternating", alternating())):
        best = min((size_report(p, max_dfa=2000) for _ in range(1 if "500" in name else 5)), key=lambda r: r["build_maps_s"])
        out.setdefault(name, {}).update({"dfa_live": best["dfa_live"], "maps_live": best["maps_live"], "build_dfa_s": round(best["build_dfa_s"], 5), "build_maps_s": round(best["build_maps_s"], 5), "maps_built_per_s": round(best["maps_live"] / best["build_maps_s"]), "table_bytes": best["table_bytes_classed"]})
    return out


def _experiments(spark, compiled: dict, cpus: int) -> dict:
    from mapmatch.operators.measure import parallel_seconds, repeated_word, scaling, small_inputs

    size = int(os.environ.get("BENCH_SYMBOLS", 1 << 27))
    workers = [w for w in (1, 2, 4, 8, 12) if w <= cpus]
    found: dict = {"symbols": size}
    for name, period in (("r5", "1111177777"), ("r50", "1" * 50 + "7" * 50), ("r500", "1" * 500 + "7" * 500), ("ra500", "a")):
        pieces = repeated_word(spark, period, size).repartition(cpus).cache()
        n = pieces.count() * (len(period) * max(1, (1 << 16) // len(period)))
        rows = scaling(pieces, compiled[name], workers)
        found[name] = {"sequential_s": round(rows[0][1], 3), "by_workers": {str(w): {"s": round(s, 3), "speed_up": round(x, 2)} for w, s, x in rows[1:]}, "symbols_per_s": round(n / rows[-1][1])}
        pieces.unpersist()
    giant = repeated_word(spark, "1111177777", 8 * size).repartition(cpus).cache()
    giant.count()
    s = parallel_seconds(giant, compiled["r5"], "maps", cpus, 1)
    found["giant"] = {"symbols": 8 * size, "s": round(s, 3), "symbols_per_s": round(8 * size / s)}
    giant.unpersist()
    rows, even = small_inputs(spark, compiled["alternating"], "0123456789", [100_000 * 4**i for i in range(6)])
    return {"scaling": found, "small_inputs": {"seconds": [[n, round(a, 4), round(b, 4)] for n, a, b in rows], "break_even": even}}


def main() -> None:
    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))
    from mapmatch.operators.match import Compiled
    from mapmatch.plans.corpora import alternating, loop, loop_or_run

    spark = _session(cpus)
    spark.sparkContext.setLogLevel("ERROR")
    found = {}
    for name, run in _queries().items():
        times = []
        for _ in range(2):
            t = time.perf_counter()
            run(spark, sf_dir).write.format("noop").mode("overwrite").save()
            times.append(time.perf_counter() - t)
        found[name] = round(min(times), 3)
    compiled = {"r5": Compiled(loop(5)), "r50": Compiled(loop(50)), "r500": Compiled(loop(500)), "ra500": Compiled(loop_or_run(500)), "alternating": Compiled(alternating())}
    for c in compiled.values():
        _ = c.maps
    more = _experiments(spark, compiled, int(cpus)) | {"kernels": _kernels(compiled)}
    print(json.dumps({"metric": "sum of query times", "value": round(sum(found.values()), 3), "unit": "sec", "queries": found, "sf": sf_dir.rsplit("sf", 1)[-1], **more}))


if __name__ == "__main__":
    main()
