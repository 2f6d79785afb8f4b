"""Every registered query runs on the smallest tables and equals its SQL twin there."""

import os
from decimal import Decimal

import duckdb
import numpy as np
import pandas as pd
import pytest

import __spark_entry__ as entry
from catalogflow import queries

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '/root/testdata/sf0.001/{t}.parquet'")
    return con


def shown(x):
    if isinstance(x, (list, dict)) or hasattr(x, "__len__"):
        return str(x)
    if pd.isna(x):
        return None
    return round(float(x), 5) if isinstance(x, (int, float, Decimal, np.number)) and not isinstance(x, bool) else str(x)


def table_of(df):
    df = df[sorted(df.columns)].astype(object)
    return sorted(repr([shown(x) for x in r]) for r in df.itertuples(index=False, name=None))


@pytest.mark.parametrize("name", sorted(queries.QUERIES))
def test_query(spark, sf, duck, name):
    got = entry.queries()[name](spark, sf).toPandas()
    if name not in queries.ORACLES:
        assert list(got.columns)
        return
    want = duck.execute(queries.ORACLES[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert table_of(got) == table_of(want)


def test_entry(spark):
    assert entry.entry(spark).count() == 6


def test_without_the_language_model_folder(tmp_path):
    """The rest imports nothing from there."""
    import shutil
    import subprocess
    import sys
    from pathlib import Path

    root = Path(entry.__file__).parent
    for f in ("catalogflow", "__spark_entry__.py"):
        (shutil.copytree if (root / f).is_dir() else shutil.copy)(root / f, tmp_path / f)
    shutil.rmtree(tmp_path / "catalogflow/llm", ignore_errors=True)
    code = "import __spark_entry__ as e; assert len(e.queries()) > 100 and not any(k.startswith(('op1_', 'pipeline')) and k != 'pipeline_summary' for k in e.queries())"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True, env=os.environ | {"PYTHONPATH": ""})
