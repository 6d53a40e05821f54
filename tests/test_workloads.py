"""Every query with a SQL twin gives the twin's rows on the smallest tables; plans push what they should."""

import os

import duckdb
import pandas as pd
import pytest

import verify
from assetmill import workloads

SF = "/root/testdata/sf0.001"
NAMES = sorted(workloads.oracle_sql())


@pytest.fixture(scope="module")
def con():
    c = duckdb.connect()
    c.execute("SET TimeZone='UTC'")
    for t in verify.TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", NAMES)
def test_twin(spark, con, name):
    got = workloads.queries()[name](spark, SF).toPandas()
    cur = con.execute(workloads.oracle_sql()[name])
    want = pd.DataFrame(cur.fetchall(), columns=[c[0] for c in cur.description])
    assert verify.canon(got).equals(verify.canon(want))


def test_entry(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() > 0


def test_filters_reach_the_scan(spark, capsys):
    workloads.queries()["op_scan_pushdown"](spark, SF).explain("formatted")
    plan = capsys.readouterr().out
    assert "GreaterThanOrEqual(l_quantity" in plan and "l_extendedprice" not in plan


def test_entry_lives_without_the_corpus_operators(tmp_path):
    import shutil
    import subprocess
    import sys

    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    shutil.copytree(f"{root}/assetmill", tmp_path / "assetmill", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(f"{root}/__spark_entry__.py", tmp_path)
    out = subprocess.run([sys.executable, "-c", "import __spark_entry__ as e; print(len(e.queries()))"], cwd=tmp_path, env={**os.environ, "PYTHONPATH": str(tmp_path)}, capture_output=True, text=True)
    assert out.returncode == 0 and int(out.stdout.split()[-1]) == len(workloads.queries())
