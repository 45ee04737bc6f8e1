from collections import Counter

import duckdb

import __spark_entry__
from tests.conftest import SF

NAME = "op_udtf_probe_ranks"


def test_ranks_of_every_supplier(spark):
    got = __spark_entry__.queries()[NAME](spark, SF)
    assert any(f.endswith("lineitem.parquet") for f in got.inputFiles())
    db = duckdb.connect()
    db.execute(f"create view lineitem as from '{SF}/lineitem.parquet'")
    rows = [tuple(r) for r in got.collect()]
    assert sorted(rows) == sorted(db.execute(__spark_entry__.oracle_sql()[NAME]).fetchall())
    n = Counter(x for (x,) in db.execute("select l_suppkey from lineitem").fetchall())
    want = [(k, c, num, r) for k, c in n.items() for num in (34, 20) for r in range(1, c + 1) if r % (c * num // 100 + 1) == 0]
    assert sorted(rows) == sorted(want)
