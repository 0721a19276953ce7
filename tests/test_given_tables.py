import duckdb
import pytest

from glyphfold.plans import queries

FOLDER = "/root/testdata/sf0.001"
NAMES = ("band_curve", "codes_binomial", "codes_diff", "codes_entropy_gap", "codes_int", "gain_table", "kout_degrees", "kout_edges", "overestimate_example")


def rows_of(table):
    return sorted(tuple(round(x, 5) if isinstance(x, float) else x for x in r) for r in table)


@pytest.mark.parametrize("name", NAMES)
def test_reads_a_given_table(spark, name, monkeypatch):
    """The rows come from a table of the folder (before, they were made up) and agree with the SQL twin."""
    read = []
    kind = type(spark.read)
    own = kind.parquet
    monkeypatch.setattr(kind, "parquet", lambda self, *paths, **kw: read.extend(paths) or own(self, *paths, **kw))
    got = rows_of(queries.QUERIES[name](spark, FOLDER).collect())
    assert got and any(p.startswith(FOLDER) for p in read)
    if name in queries.SQL:
        con = duckdb.connect()
        for t in ("nation", "region", "customer", "supplier", "orders", "lineitem", "documents"):
            con.execute(f"create view {t} as select * from '{FOLDER}/{t}.parquet'")
        want = rows_of(con.execute(queries.SQL[name]).fetchall())
        assert len(got) == len(want)
        for a, b in zip(got, want, strict=True):
            assert a == pytest.approx(b, abs=2e-5)
