import re

import duckdb
import pytest

from pullgraph import oracles, queries
from tests.conftest import SF

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
QUICK = [k for k in queries.queries() if re.search(r"_(trade|link)$|^(memory_aa|od_cross|explosion|cache_mode|components|event_edges|degree_rollup|labels|graph_stats|load)", k) and not re.search(r"gas|hadoop|disk|ondemand|compare|agreement|times|measured", k)]


@pytest.fixture(scope="module")
def con():
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", QUICK)
def test_query_equals_sql(spark, con, name):
    got = queries.queries()[name](spark, SF).toPandas()
    sql = oracles.oracle_sql().get(name)
    if sql is None:
        assert len(got)
        return
    want = con.execute(sql).df()
    cols = sorted(got.columns)
    assert cols == sorted(want.columns)
    a, b = (x[cols].sort_values(cols).reset_index(drop=True).astype(object) for x in (got, want))
    assert len(a) == len(b) and (a == b).all().all()
