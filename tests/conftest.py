import sys
from pathlib import Path

import numpy as np
import pandas as pd
import pytest

ROOT = Path(__file__).resolve().parent.parent
sys.path.insert(0, str(ROOT))
TESTDATA = "/root/testdata"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="session")
def spark():
    import os

    os.environ["PYTHONPATH"] = f"{ROOT}:{os.environ.get('PYTHONPATH', '')}"
    from graphwin.session import local_session

    s = local_session(4, 4, **{"spark.driver.memory": "3g", "spark.sql.warehouse.dir": "/tmp/checkpoints/warehouse"})
    s.sparkContext.setLogLevel("ERROR")
    yield s
    s.stop()


@pytest.fixture(scope="session")
def tiny_dir():
    return f"{TESTDATA}/sf0.001"


@pytest.fixture(scope="session")
def duck(tiny_dir):
    import duckdb

    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{tiny_dir}/{t}.parquet'")
    return con


def normal(frame):
    """Rows as sorted text, columns by name. Spark and DuckDB results are read as Python values: pandas would turn whole
    numbers beside nulls into floats."""
    if hasattr(frame, "collect"):
        names, rows = frame.columns, [tuple(r) for r in frame.collect()]
    elif hasattr(frame, "fetchall"):
        names, rows = [c[0] for c in frame.description], frame.fetchall()
    else:
        names, rows = list(frame.columns), frame.astype(object).itertuples(index=False, name=None)
    order = sorted(range(len(names)), key=lambda k: names[k])

    def cell(v):
        if pd.api.types.is_scalar(v) and pd.isna(v):
            return None
        if isinstance(v, (float, np.floating)):
            return round(float(v), 9)
        if isinstance(v, (list, tuple, np.ndarray)):
            return [cell(x) for x in v]
        return int(v) if type(v).__name__.startswith(("int", "uint")) else v

    return [[names[k] for k in order], *sorted(repr(tuple(cell(row[k]) for k in order)) for row in rows)]
