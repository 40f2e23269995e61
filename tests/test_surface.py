"""SQL functions and the wider relational surface against DuckDB."""

import duckdb
import pytest

from rankpress.functions import sql
from rankpress.plans import surface


@pytest.fixture(scope="module")
def con(sf):
    c = duckdb.connect()
    for t in ("documents", "events"):
        c.sql(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", sorted(surface.QUERIES))
def test_query_matches_its_sql(spark, sf, con, name):
    a, b = surface.QUERIES[name](spark, sf).toPandas(), con.sql(surface.SQL[name]).df()
    cols = sorted(a.columns)
    rows = lambda x: sorted(tuple(None if v is None or v != v else f"{v:.5f}" if isinstance(v, float) else str(v) for v in r).__repr__() for r in x[cols].astype(object).itertuples(index=False))
    plain = lambda x: x.apply(lambda c: c.astype(float) if c.dtype.kind in "iuf" else c)
    assert cols == sorted(b.columns) and rows(plain(a)) == rows(plain(b))


def test_functions_keep_nulls_and_the_empty_text(spark):
    sql.register(spark)
    r = spark.sql("select id, rp_compress(t, 'gzip') is null z, rp_decompress(rp_compress(t, 'huffman'), 'huffman') t, size(rp_encode(t, 'byte')) n from values (1, null), (2, ''), (3, 'é.') as x(id, t)").orderBy("id").collect()
    assert [(x.z, x.t, x.n) for x in r] == [(True, None, None), (False, "", 0), (False, "é.", 3)]
    assert spark.sql("select * from values (cast(null as string)), ('ab') as x(t), lateral rp_tokens(x.t, 'byte')").count() == 2


def test_huffman_bits():
    assert [sql.total_huffman_bits(c) for c in ([], [7], [1, 1], [1, 1, 2], [5, 0, 5])] == [0, 7, 2, 6, 10]
