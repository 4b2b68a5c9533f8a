"""Compare queries with their DuckDB SQL: python -m tests.compare [SF_DIR] [NAME...]."""

from __future__ import annotations

import sys
import time
from decimal import Decimal
from pathlib import Path

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def _plain(v):
    if isinstance(v, float):
        return round(v, 9)
    if isinstance(v, Decimal):
        return float(v)
    return v


def rows_of(frame) -> list[tuple]:
    cols = sorted(frame.columns)
    return sorted((tuple(_plain(v) for v in r) for r in frame[cols].itertuples(index=False, name=None)), key=repr)


def differences(spark, query, sql: str, sf_dir: str) -> list[str]:
    con = duckdb.connect()
    for t in TABLES:
        if Path(f"{sf_dir}/{t}.parquet").exists():
            con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf_dir}/{t}.parquet')")
    df = query(spark, sf_dir)
    got, want = df.toArrow(), con.execute(sql).to_arrow_table()
    if sorted(got.column_names) != sorted(want.column_names):
        return [f"columns {sorted(got.column_names)} and {sorted(want.column_names)}"]
    a = sorted(zip(*[map(_plain, got[c].to_pylist()) for c in sorted(got.column_names)], strict=True), key=repr)
    b = sorted(zip(*[map(_plain, want[c].to_pylist()) for c in sorted(got.column_names)], strict=True), key=repr)
    out = [f"rows {len(a)} and {len(b)}"] if len(a) != len(b) else []
    types = {c: (str(got[c].type), str(want[c].type)) for c in got.column_names if str(got[c].type) != str(want[c].type)}
    if types:
        print("    types differ:", types)
    return out + [f"{x} and {y}" for x, y in zip(a, b, strict=False) if x != y][:5]


def main(args: list[str]) -> int:
    sys.path.insert(0, str(Path(__file__).resolve().parent.parent))
    import __spark_entry__ as e
    from overlapsolve.session import local_session

    sf_dir = args[0] if args else "/root/testdata/sf0.01"
    spark = local_session(8, 8)
    spark.sparkContext.setLogLevel("ERROR")
    queries, sql, bad = e.queries(), e.oracle_sql(), 0
    for name in args[1:] or queries:
        t = time.time()
        if name in sql:
            d = differences(spark, queries[name], sql[name], sf_dir)
        else:
            n = queries[name](spark, sf_dir).count()
            d = []
            print(f"  {name}: {n} rows, no SQL")
        bad += bool(d)
        print(f"{'BAD' if d else 'ok '} {name} {time.time() - t:.1f} s", *d, sep="\n    " if d else " ", flush=True)
    return bad


if __name__ == "__main__":
    sys.exit(main(sys.argv[1:]))
