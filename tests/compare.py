"""Run a registered query and its SQL side by side."""

import duckdb
import pandas as pd

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def database(sf_dir):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf_dir}/{t}.parquet')")
    return con


def rows(frame):
    cols = sorted(frame.columns)
    values = [tuple(None if pd.isna(v) else v.item() if hasattr(v, "item") else v for v in r) for r in frame[cols].itertuples(index=False)]
    return cols, sorted(values, key=lambda r: tuple((x is None, str(type(x)), x) for x in r))
