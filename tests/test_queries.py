"""Every query of the engine against its SQL twin on the smallest tables."""

import math
import os
from collections import Counter

import duckdb
import pytest

from distinct_bounds.plans import catalogue

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        path = f"{SF}/{t}.parquet"
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{path + '/*.parquet' if os.path.isdir(path) else path}'")
    return con


def plain(row):
    return tuple("nan" if isinstance(v, float) and math.isnan(v) else round(v, 6) if isinstance(v, float) else v for v in row)


@pytest.mark.parametrize("name", sorted(catalogue.queries()))
def test_query(spark, duck, name):
    df = catalogue.queries()[name](spark, SF)
    names = sorted(df.columns)
    got = Counter(plain(r) for r in df.select(*names).collect())
    text = catalogue.oracle_sql().get(name)
    if text is None:
        assert got
        return
    duck.execute(f"CREATE OR REPLACE TEMP TABLE want AS {text}")
    quoted = ", ".join(f'"{n}"' for n in names)
    want = Counter(plain(r) for r in duck.execute(f"SELECT {quoted} FROM want").fetchall())
    assert sorted(c[0] for c in duck.execute("DESCRIBE want").fetchall()) == names
    assert got == want


def test_flagship(spark):
    df = catalogue.flagship(spark, SF)
    assert df.count() > 80 and {"slice", "estimate", "lower", "upper", "truth", "covered"} <= set(df.columns)
