import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parents[1]))


@pytest.fixture(scope="session")
def spark():
    from linkveil.session import local_session

    session = local_session("linkveil-tests", "4", 4)
    session.sparkContext.setLogLevel("ERROR")
    yield session
    session.stop()


@pytest.fixture(scope="session")
def sf_dir():
    return "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def duck(sf_dir):
    duckdb = pytest.importorskip("duckdb")
    con = duckdb.connect(config={"memory_limit": "4GB", "threads": 4})
    for path in Path(sf_dir).glob("*.parquet"):
        con.execute(f"CREATE VIEW {path.stem} AS SELECT * FROM '{path}{'/*.parquet' if path.is_dir() else ''}'")
    return con


def rows_of(frame):
    """Rows as comparable tuples by sorted column names, numbers rounded."""
    names = sorted(frame.columns)

    def plain(v):
        if v is None or type(v).__name__ == "NAType" or v != v:
            return "null"
        if hasattr(v, "tolist"):
            v = v.tolist()
        if isinstance(v, bool):
            return str(v)
        if isinstance(v, (int, float)):
            return f"{float(v):.7f}"
        return str(v)

    return sorted(tuple(plain(v) for v in row) for row in frame[names].itertuples(index=False))
