import subprocess
import sys
from pathlib import Path

import pytest

ROOT = Path(__file__).resolve().parents[1]


def test_entry_runs(spark):
    import __spark_entry__ as e

    assert e.entry(spark).columns == ["e1", "e2", "sim"]
    assert set(e.oracle_sql()) <= set(e.queries())


def test_library_works_without_the_text_operators():
    code = "import sys; sys.modules['allpairs.llm'] = None; sys.modules['corpus_pipeline'] = None; import __spark_entry__ as e; print(len(e.queries()))"
    out = subprocess.run([sys.executable, "-c", code], cwd=ROOT, capture_output=True, text=True, check=True)
    assert int(out.stdout.split()[-1]) > 150


def plain(table):
    """Rows in any order, columns by name, numbers and nulls alike however a library types them."""
    import pandas as pd

    same = lambda v: None if pd.isna(v) else float(v) if isinstance(v, (int, float)) else str(v)
    return sorted(repr([same(v) for v in r]) for r in table[sorted(table.columns)].astype(object).values.tolist())


def test_some_statements_match(spark):
    import duckdb

    from allpairs import catalog

    c = duckdb.connect()
    where = "/root/testdata/sf0.001"
    for name in ("lineitem", "documents", "events", "supplier", "nation"):
        c.execute(f"CREATE VIEW {name} AS SELECT * FROM '{where}/{name}.parquet'")
    for name in ("pairs_ruzicka_doc_shingles", "joined_sharding_c32", "pairs_chunked_t4", "uni_totals_user_props", "op_join_as_of"):
        df = catalog.queries()[name](spark, where)
        want = c.execute(catalog.oracle_sql()[name]).fetchdf()
        assert plain(df.toPandas()) == plain(want), name


def events(tmp_path, rows, columns):
    """An events table of these rows for Spark and for DuckDB."""
    import duckdb

    c = duckdb.connect()
    c.execute(f"COPY (SELECT * FROM (VALUES {', '.join(rows)}) v({columns})) TO '{tmp_path}/events.parquet' (FORMAT parquet)")
    c.execute(f"CREATE VIEW events AS SELECT * FROM '{tmp_path}/events.parquet'")
    return c


@pytest.mark.parametrize("name", ["op_window_range_frame", "op_window_sessions"])
def test_seconds_are_rounded_as_in_the_statement(spark, tmp_path, name):
    """A day and fractions of a second apart: truncated seconds are within the day, rounded ones aren't, and the other way round."""
    from allpairs import catalog

    ends = {1: ("00:00:00.2", "00:00:00.7"), 2: ("00:00:00.7", "00:00:01.4"), 3: ("00:00:00.5", "00:00:01.5"), 4: ("00:00:01.5", "00:00:02.5")}
    rows = [f"({user * 10 + k}::BIGINT, {user}::BIGINT, 'view', TIMESTAMP '2024-01-0{1 + k} {time}', 1.0::DOUBLE)" for user, times in ends.items() for k, time in enumerate(times)]
    c = events(tmp_path, rows, "event_id, user_id, event_type, ts, value")
    assert plain(catalog.queries()[name](spark, str(tmp_path)).toPandas()) == plain(c.execute(catalog.oracle_sql()[name]).fetchdf())


def test_a_registered_measure_reaches_its_threshold(spark, tmp_path):
    """(4 / 6 + 4 / 30) / 2 is 0.4, but its fractions add up to less."""
    from allpairs import catalog

    kept = [(1, k) for k in range(6)] + [(2, k) for k in range(2, 32)]
    c = events(tmp_path, [f"""({user}::BIGINT, '{{"k": {k}}}')""" for user, k in kept], "user_id, props")
    name = "pairs_registered_measure_user_props"
    want = c.execute(catalog.oracle_sql()[name]).fetchdf()
    assert len(want) == 1
    assert plain(catalog.queries()[name](spark, str(tmp_path)).toPandas()) == plain(want)
