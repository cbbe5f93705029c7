import subprocess
import sys

import __spark_entry__ as entry


def test_names():
    q, o = entry.queries(), entry.oracle_sql()
    assert set(o) <= set(q)
    assert "mwm_catalog" in q


def test_flagship(spark):
    rows = entry.entry(spark).collect()
    assert len(rows) == 1 and rows[0]["value"] > 0


def test_nothing_else_needs_the_llm_subpackage():
    code = "import sys; sys.modules['treefold.llm'] = None\nimport treefold.queries, treefold.measures, treefold.streaming, treefold.sources; print('fine')"
    assert "fine" in subprocess.run([sys.executable, "-c", code], capture_output=True, text=True, cwd=entry.__file__.rsplit("/", 1)[0]).stdout


def test_relational_against_sql(spark, sf):
    import duckdb

    from treefold.operators.relational import OPS

    con = duckdb.connect()
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "pages"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    for name in ("op_degree_count", "op_last_view_before_purchase", "op_nested_interval_ancestor", "op_rollup_region_nation", "op_user_chain"):
        run, sql = OPS[name]
        df = run(spark, sf)
        cols = sorted(df.columns)
        got = sorted(str(tuple(r[c] for c in cols)) for r in df.collect())
        rel = con.sql(sql)
        want = sorted(str(tuple(dict(zip(rel.columns, r))[c] for c in cols)) for r in rel.fetchall())
        assert got == want, name
