"""A query's rows against its SQL in DuckDB."""

import numpy as np

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connect(sf_dir):
    import duckdb

    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf_dir}/{t}.parquet')")
    return con


def rows(df):
    """Rows as text, columns by name, numbers as rounded doubles."""
    df = df[sorted(df.columns)].astype(object)
    df = df.where(df.notna(), None)
    one = lambda v: round(float(v), 6) + 0.0 if isinstance(v, (int, float, np.integer, np.floating)) and not isinstance(v, bool) else v
    return sorted(str(tuple(map(one, r))) for r in df.itertuples(index=False, name=None))
