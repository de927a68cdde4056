"""Size, fold and equivalence queries take their symbols, words and patterns from the given tables."""

import datetime

import duckdb
import pytest

from mapmatch.plans.workloads import ORACLES, QUERIES

#: The rows of the small tables, or how many there are.
MOVED = {
    "closure_size_alt5": [(11, 10, 3, 2)],
    "closure_size_r5": [(11, 10, 7, 6)],
    "closure_size_ra5": [(13, 12, 8, 7)],
    "closure_size_w10": [(5, 4, 2, 2)],
    "closure_size_w9": [(32, 31, 2, 1)],
    "chunk_maps_ab": 4,
    "closure_distributed": [(2, 1)],
    "equivalences": [("(click|view)*", "(error|view)*", False, "click")],
    "fold_ab": [(1, "2024-01-01", 1, "1,2,2"), (1, "2024-01-02", 0, "0,2,2"), (2, "2024-01-01", 2, "2,2,2")],
    "loop_sizes": 4,
    "map_blowup_sizes": [(2, 4), (3, 27)],
    "map_table_ab": [("0,1,2", True), ("2,2,2", False)],
}


@pytest.fixture(scope="module")
def small(spark, tmp_path_factory):
    """Tables that hold few of the patterns' symbols and sizes."""
    folder = str(tmp_path_factory.mktemp("small"))
    at = datetime.datetime(2024, 1, 1)
    events = [(i, at + datetime.timedelta(hours=h), u, e) for i, (h, u, e) in enumerate([(0, 1, "view"), (1, 1, "click"), (2, 1, "view"), (24, 1, "view"), (25, 1, "error"), (0, 2, "click"), (1, 2, "view"), (2, 2, "view"), (3, 2, "view"), (4, 2, "view")])]
    spark.createDataFrame(events, "event_id long, ts timestamp, user_id long, event_type string").write.parquet(f"{folder}/events.parquet")
    lines = [(i, n, float(q), "A") for i, (n, q) in enumerate([(1, 2), (2, 2), (3, 4), (2, 2)])]
    spark.createDataFrame(lines, "l_orderkey long, l_linenumber int, l_quantity double, l_returnflag string").write.parquet(f"{folder}/lineitem.parquet")
    spark.createDataFrame([(1, "ttt"), (2, None), (3, "")], "doc_id long, text string").write.parquet(f"{folder}/documents.parquet")
    return folder


@pytest.mark.parametrize("name", MOVED)
def test_moved_queries_follow_their_tables(spark, small, tmp_path, name):
    con = duckdb.connect()
    for tab in ("events", "lineitem", "documents"):
        con.execute(f"CREATE VIEW {tab} AS SELECT * FROM '{small}/{tab}.parquet/*.parquet'")
    sort = lambda rows: sorted(map(tuple, rows), key=lambda r: [(x is None, str(x)) for x in r])
    want = sort(con.execute(ORACLES[name]).fetchall())
    assert sort(QUERIES[name](spark, small).collect()) == want
    assert MOVED[name] in (want, len(want))
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        QUERIES[name](spark, str(tmp_path)).collect()


def test_size_reports_of_no_pattern(spark):
    from mapmatch.operators import measure

    rows = spark.createDataFrame([], "pattern_id int, family string, pattern string, mode string")
    assert measure.corpus_sizes(rows, parts=2).collect() == []
