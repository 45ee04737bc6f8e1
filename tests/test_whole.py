import duckdb
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.01"
TABLES = ("lineitem", "part", "documents", "events")


def compared(spark, name):
    """The rows of a query, which its SQL must give too."""
    con = duckdb.connect()
    con.execute("set timezone = 'UTC'")
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    df = entry.queries()[name](spark, SF)
    got = sorted((tuple(r) for r in df.collect()), key=repr)
    columns = ", ".join(f'"{c}"' for c in df.columns)
    assert got == sorted(con.execute(f"select {columns} from ({entry.oracle_sql()[name]})").fetchall(), key=repr)
    return got


def test_sequence_access_reads_every_position(spark):
    got = compared(spark, "sequence_access")
    assert len(got) == spark.read.parquet(f"{SF}/part.parquet").count()


def test_rank_and_select_reach_the_end(spark):
    n = spark.read.parquet(f"{SF}/part.parquet").count()
    got = compared(spark, "sequence_rank_select")
    assert sum(r[3] for r in got if r[0] == "rank" and r[2] == n) == n


def test_report_of_all_rectangles(spark):
    assert {r[0] for r in compared(spark, "report_rect")} >= {1, 2, 3, 6}


@pytest.mark.parametrize("name", ["majority_rect_D_02", "mode_rect_D", "index_majority_D_005", "majority_fixed_D_1_5_asked_1_2"])
def test_documents_beyond_the_first(spark, name):
    compared(spark, name)


def test_rectangles_reach_all_documents(spark):
    got = compared(spark, "op_map_value_histogram")
    assert sum(r[2] for r in got if r[0] == 4) == spark.read.parquet(f"{SF}/documents.parquet").count()


@pytest.mark.parametrize("name", ["op_win_tumbling", "op_win_sliding", "op_win_session"])
def test_windows_of_all_users(spark, name):
    got = compared(spark, name)
    assert sum(r[-2] for r in got) == spark.read.parquet(f"{SF}/events.parquet").count() * (2 if "sliding" in name else 1)
