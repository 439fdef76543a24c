import duckdb
import pytest

from stripmatch import relational, workloads

SF = "/root/testdata/sf0.001"
NAMES = sorted(k for k, (f, _) in workloads._registered.items() if f.__module__ == relational.__name__)


@pytest.mark.parametrize("name", NAMES)
def test_against_sql(spark, name):
    c = duckdb.connect()
    for t in ("lineitem", "part", "orders", "customer", "supplier", "nation", "region", "embeddings", "events"):
        c.sql(f"create view {t} as select * from '{SF}/{t}.parquet'")
    got = workloads.queries()[name](spark, SF).toPandas()
    want = c.sql(workloads.oracle_sql()[name]).df()
    cols = sorted(got.columns)
    assert cols == sorted(want.columns)
    key = lambda d: sorted(map(tuple, d[cols].astype(object).where(d[cols].notna(), None).itertuples(index=False)), key=str)
    a, b = key(got), key(want)
    assert len(a) == len(b)
    unlike = [(x, y) for x, y in zip(a, b) if str(x) != str(y) and any(p != q for p, q in zip(x, y))]
    assert not unlike, unlike[:2]
