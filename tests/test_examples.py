import os

import duckdb
import pytest

from depmine.queries import QUERIES, SQL

NAMES = ["columns_deal_lineitem", "cost_bounds_model", "example_four_rows_classes", "example_four_rows_evidence", "example_four_rows_fds", "example_four_rows_keys", "example_four_rows_meetings", "example_tax_constraint", "example_tax_constraint_found", "example_tax_evidence", "example_tax_fds", "example_tax_keys"]


@pytest.mark.parametrize("name", NAMES)
def test_examples_come_from_tables(spark, tiny, name):
    """Without the tables there is no result, and with them that of the SQL."""
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        QUERIES[name](spark, "/tmp/no-such-tables").collect()
    con = duckdb.connect()
    for f in os.listdir(tiny):
        con.execute(f"create view {f.removesuffix('.parquet')} as select * from '{tiny}/{f}'")
    found, want = QUERIES[name](spark, tiny), con.execute(SQL[name])
    columns = [d[0] for d in want.description]
    assert sorted(found.columns) == sorted(columns)
    assert sorted(map(repr, (tuple(r[c] for c in columns) for r in found.collect()))) == sorted(map(repr, want.fetchall()))
