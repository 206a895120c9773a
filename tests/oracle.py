"""Compares queries with their SQL: python tests/oracle.py [folder] [name prefix ...]"""

import sys
import time
from pathlib import Path

import duckdb

sys.path.insert(0, str(Path(__file__).resolve().parents[1]))
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def database(sf_dir):
    con = duckdb.connect()
    con.sql("SET TimeZone = 'UTC'")
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    return con


def rows(frame):
    import pandas as pd

    f = frame[sorted(frame.columns)]
    out = []
    for r in f.itertuples(index=False):
        out.append(tuple("" if x is None or (not isinstance(x, (list, dict)) and pd.isna(x)) else f"{float(x):.6g}" if isinstance(x, float) else str(x) for x in r))
    return sorted(out)


def differ(spark_df, con, sql):
    """None, or what differs."""
    want = con.sql(sql).df()
    got = spark_df.toPandas()
    if sorted(got.columns) != sorted(want.columns):
        return f"columns {sorted(got.columns)} and {sorted(want.columns)}"
    a, b = rows(got), rows(want)
    for f in spark_df.schema:  # pandas turns a whole number column with nulls into floats on one side and keeps it on the other
        if f.dataType.typeName() == "long" and str(want[f.name].dtype) == "Int64":
            got[f.name] = got[f.name].astype("Int64")
    if a != b:
        only = [x for x in a if x not in set(b)][:2], [x for x in b if x not in set(a)][:2]
        return f"{len(a)} and {len(b)} rows; {only}"
    kinds = {c: (str(got[c].dtype), str(want[c].dtype)) for c in got.columns if got[c].dtype != want[c].dtype and len(got)}
    return f"types {kinds}" if kinds and any("datetime" not in k[0] for k in kinds.values()) else None


if __name__ == "__main__":
    from conftest import session

    import __spark_entry__ as entry

    folder, names = (sys.argv[1] if len(sys.argv) > 1 else "/root/testdata/sf0.01"), sys.argv[2:]
    spark, con, sqls = session(), database(folder), entry.oracle_sql()
    for k, f in entry.queries().items():
        if (names and not any(k.startswith(n) for n in names)) or (not names and (k.startswith("op") or k == "pipeline")):
            continue
        t = time.time()
        try:
            said = differ(f(spark, folder), con, sqls[k]) if k in sqls else f"rows only: {f(spark, folder).count()}"
        except Exception as e:  # noqa: BLE001
            said = "ERROR " + str(e).replace("\n", " ")[:700]
        print(f"{k} {time.time() - t:.1f}s {'ok' if said is None else said}", flush=True)
