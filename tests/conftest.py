import os

import pytest

os.environ.setdefault("PYTHONPATH", os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
SMALL, MIDDLE = "/root/testdata/sf0.001", "/root/testdata/sf0.01"


@pytest.fixture(scope="session")
def spark():
    from tourspark.session import local_session

    session = local_session("8", 8, "6g")
    session.sparkContext.setLogLevel("ERROR")
    yield session
    from tourspark.session import clear_stages

    clear_stages(session)
    session.stop()


@pytest.fixture(scope="session")
def duck():
    """A function: rows of a SQL text over the tables of a folder, as sorted tuples."""
    import glob

    import duckdb

    def ask(sql: str, sf_dir: str = SMALL):
        con = duckdb.connect()
        con.execute("SET timezone = 'UTC'")
        for p in glob.glob(f"{sf_dir}/*.parquet"):
            con.execute(f"CREATE VIEW {os.path.basename(p)[:-8]} AS SELECT * FROM '{p}'")
        found = con.execute(sql)
        names = [d[0] for d in found.description]
        order = sorted(range(len(names)), key=names.__getitem__)
        return [names[i] for i in order], sorted(tuple(map(_plain, (r[i] for i in order))) for r in found.fetchall())

    return ask


def _plain(x):
    return repr(round(x, 9) if isinstance(x, float) else x)


@pytest.fixture(scope="session")
def rows_of():
    """A function: column names and sorted rows of a DataFrame, in the form of ``duck``."""

    def read(df):
        names = sorted(df.columns)
        return names, sorted(tuple(_plain(r[c]) for c in names) for r in df.collect())

    return read
