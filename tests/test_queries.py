"""Every query of the reference's own operators against its SQL, on the smallest tables."""

import duckdb
import numpy as np
import pytest

from predmap import workloads

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
LONG = {"model_table", "space_table", "control_table", "sweep_gauss", "hard_slices", "ablation_table", "comparison_pivot", "savings_table"}


def rows(df):
    df = df[sorted(df.columns)]
    text = lambda v: str(round(float(v), 6)) if isinstance(v, (int, float, np.integer, np.floating, np.bool_)) else str(v)
    return sorted(map(tuple, df.astype(object).where(df.notna(), None).map(text).values.tolist()))


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", sorted(set(workloads.queries()) - LONG))
def test_query(spark, duck, name):
    got = workloads.queries()[name](spark, SF).toPandas()
    sql = workloads.oracle_sql().get(name)
    if sql:
        assert rows(got) == rows(duck.execute(sql).df())
    else:
        assert len(got)


def test_registry_without_the_optional_part():
    import subprocess
    import sys

    code = "import sys; sys.modules['predmap.llm'] = None; sys.modules['corpus_pipeline'] = None; import __spark_entry__ as e; print(len(e.queries()), len(e.oracle_sql()))"
    out = subprocess.run([sys.executable, "-c", code], capture_output=True, text=True, cwd=__file__.rsplit("/tests/", 1)[0])
    assert out.returncode == 0 and int(out.stdout.split()[0]) == len(workloads.queries())
