"""Every registered query that has SQL gives the rows of its SQL, on the smallest tables."""

import os

import duckdb
import pytest
from pyspark.errors import AnalysisException

from winnow.plans import catalog

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return con


def plain(v):
    if v is None or isinstance(v, float) and v != v:
        return "-"
    if isinstance(v, bool):
        return str(v)
    if isinstance(v, (list, tuple)):
        return ",".join(map(plain, v))
    try:
        return repr(float(v))
    except (TypeError, ValueError):
        return str(v)


@pytest.mark.parametrize("name", sorted(catalog.oracle_sql()))
def test_query_equals_its_sql(spark, sf, duck, name):
    df = catalog.queries()[name](spark, sf)
    cur = duck.execute(catalog.oracle_sql()[name])
    cols = sorted(df.columns)
    at = [c[0] for c in cur.description]
    assert sorted(at) == cols
    want = sorted(tuple(plain(r[at.index(c)]) for c in cols) for r in cur.fetchall())
    assert sorted(tuple(plain(r[c]) for c in cols) for r in df.collect()) == want


ROWS_ONLY = sorted(set(catalog.queries()) - set(catalog.oracle_sql()))
SLOW = {"selection_comparison", "gain_and_retention", "open_domain_choice", "size_pair", "f1_by_size"}


@pytest.mark.parametrize("name", [n for n in ROWS_ONLY if n not in SLOW])
def test_other_queries_run(spark, sf, name):
    assert catalog.queries()[name](spark, sf).count() >= 0
    assert os.path.isdir(sf)


@pytest.mark.parametrize("name", ["cost_ledger", "delta_pct", "published_observations", "published_replay", "win_rate", "win_rate_with_self"])
def test_figures_come_from_the_given_tables(spark, sf, tmp_path, name):
    missing = {"published_replay": "documents", "cost_ledger": "conversations"}.get(name, "labels")
    for t in TABLES:
        if t != missing:
            os.symlink(f"{sf}/{t}.parquet", tmp_path / f"{t}.parquet")
    with pytest.raises(AnalysisException, match=missing):
        catalog.queries()[name](spark, str(tmp_path)).collect()
