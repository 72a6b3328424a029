"""Running DuckDB SQL on the given tables and comparing rows whatever their order."""

import datetime
import math
import os

import duckdb
import pandas as pd

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connect(folder):
    con = duckdb.connect()
    con.execute("SET timezone = 'UTC'")
    for t in TABLES:
        path = f"{folder}/{t}.parquet"
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{path if os.path.isfile(path) else path + '/*.parquet'}'")
    return con


def _plain(x):
    if x is None or x is pd.NaT or x is pd.NA:
        return None
    if isinstance(x, (pd.Timestamp, datetime.datetime, datetime.date)):
        return str(x).replace(" 00:00:00", "")
    if isinstance(x, str):
        return x
    number = float(x)
    return None if math.isnan(number) else round(number, 6) + 0.0


def rows(frame):
    frame = frame[sorted(frame.columns)]
    return sorted((tuple(_plain(x) for x in r) for r in frame.itertuples(index=False)), key=repr)
