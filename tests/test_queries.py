"""Registered queries against their SQL in DuckDB, on the smallest tables."""

import math

import duckdb
import pytest

from softlanes.plans import catalogue

SKIP_SLOW = {"mse_vs_deadline", "mse_by_scheme", "peak_to_average", "ratio_rep_over_coded", "restart_converged_segment"}
NAMES = sorted(set(catalogue.oracle_sql()) - SKIP_SLOW)
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck(small):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{small}/{t}.parquet'")
    return con


def rows(pdf):
    def norm(v):
        if v is None or (isinstance(v, float) and math.isnan(v)) or str(v) in ("NaT", "<NA>"):
            return None
        if isinstance(v, float):  # whole numbers beside nulls come as floats from either engine
            return int(v) if v == int(v) else round(float(v), 7)
        return int(v) if hasattr(v, "__int__") and not isinstance(v, str) else str(v)

    cols = sorted(pdf.columns)
    return cols, sorted(str([norm(v) for v in r]) for r in pdf[cols].astype(object).values.tolist())


def test_every_oracle_has_a_query():
    assert set(catalogue.oracle_sql()) <= set(catalogue.queries())
    assert len(catalogue.queries()) > 90


@pytest.mark.parametrize("name", NAMES)
def test_query_matches_sql(spark, duck, small, name):
    assert rows(catalogue.queries()[name](spark, small).toPandas()) == rows(duck.sql(catalogue.oracle_sql()[name]).df())


@pytest.mark.parametrize("name", [
    "bound_uncoded", "bound_coded_parity", "bound_schur_one_spare", "bound_correlated", "code_complement", "code_dft", "code_dft_gram", "code_gaussian", "code_hartley",
    "code_identity", "code_parity", "code_reports",
])
def test_bounds_and_codes_come_from_a_table(spark, tmp_path, name):
    with pytest.raises(Exception, match="PATH_NOT_FOUND|does not exist"):
        catalogue.queries()[name](spark, str(tmp_path)).collect()
